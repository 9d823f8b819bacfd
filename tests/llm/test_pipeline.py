import numpy as np
import pandas as pd

import corpus_pipeline as P
from vecengine.llm import ngram_join

WORDS = [f"{a}{b}" for a in ("sun", "moon", "tree", "river", "stone", "bird") for b in ("", "light", "side", "s", "fall")]


def tables(spark, path):
    """300 texts of which a third is toxic or poor, and copies; some rows odd."""
    rng = np.random.default_rng(2)
    rows, marks = [], []
    for i in range(300):
        words = rng.choice(WORDS, 40).tolist()
        toxic, poor = i % 7 == 0, i % 5 == 0
        text = " ".join(words + ["vile", "vermin"] * 2 * toxic)
        rows.append((i, "#!% " * 40 + text.upper()[:40] if poor else text))
        marks.append((i, int(not poor), int(toxic)))
    rows += [(1000 + i, rows[3][1] + (" end" if i % 2 else "")) for i in range(6)]
    rows += [(2000, None), (2001, ""), (2002, "moon " * 4000), (None, "river " * 9)]
    d = pd.DataFrame([(i, t, "en", "web", len(t or "")) for i, t in rows], columns=["doc_id", "text", "lang", "source", "n_chars"]).astype({"doc_id": "Int64"})
    d = d.astype(object).where(d.notna(), None)
    schema = "doc_id long, text string, lang string, source string, n_chars long"
    spark.createDataFrame([tuple(r) for r in d.itertuples(index=False)], schema).write.parquet(f"{path}/documents.parquet")
    spark.createDataFrame(marks, "doc_id long, quality int, toxic int").write.parquet(f"{path}/labels.parquet")


def test_each_stage_takes_effect(spark, tmp_path):
    tables(spark, tmp_path)
    path = f"file://{tmp_path}"
    docs, labels = (spark.read.parquet(f"{path}/{t}.parquet").coalesce(2) for t in ("documents", "labels"))
    ids = lambda df: sorted((-1 if r[0] is None else r[0]) for r in df.select("doc_id").collect())
    for (name, stage), column, good in ((P.STAGES[0], "toxic", 0), (P.STAGES[1], "quality", 1)):
        kept = stage(spark, docs, path)
        assert kept.columns == docs.columns, name
        left = ids(kept)
        assert len([i for i, y in labels.select("doc_id", column).collect() if (i in left) != (y == good)]) < 15 and 2002 in left
    kept = P.drop_near_copies(spark, docs, path)
    assert kept.columns == docs.columns
    comp = ngram_join.jaccard_components(docs, 5, 80, 100).collect()
    gone = {r["doc_id"] for r in comp if r["component_id"] != r["doc_id"]}
    assert gone >= {1000, 1002, 1004} and ids(kept) == sorted(i for i in ids(docs) if i not in gone)


def test_the_whole_and_an_empty_table(spark, tmp_path):
    tables(spark, tmp_path)
    path = f"file://{tmp_path}"
    out = P.run(spark, path).toPandas()
    assert (out.offset + out.length <= out.capacity).all() and not out.doc_id.isin([7, 1000]).any() and {1, 2, 3} <= set(out.doc_id.dropna())
    bins = out.groupby("bin").agg(used=("length", "sum"), capacity=("capacity", "first"))
    assert (bins.used <= bins.capacity).all()
    docs = spark.read.parquet(f"{path}/documents.parquet").where("false")
    for _, stage in P.STAGES:
        docs = stage(spark, docs, path)
        assert docs.count() == 0 or _ == "packing"
