import numpy as np
import pytest
from pyspark.sql import functions as F

from vecengine.llm import common, near_vectors, sharding, topk


def frame(spark, x):
    return spark.createDataFrame([(i, None if v is None else [None if c is None else float(c) for c in v]) for i, v in enumerate(x)], "vec_id long, embedding array<float>")


def test_near_vectors_against_brute_force(spark):
    rng = np.random.default_rng(2)
    x = rng.normal(size=(60, 16))
    x = np.concatenate((x, x[:30] + rng.normal(size=(30, 16)) * 0.05, x[:5] * 3, x[:5]))
    odd = [None, [0.0] * 16, [float("nan")] * 16, [None] * 16, [1.0] * 3]
    got = near_vectors.near_vectors(frame(spark, [*x, *odd])).orderBy("vec_id").toPandas()
    f = x.astype(np.float32).astype(float)
    u = f / np.linalg.norm(f, axis=1, keepdims=True)
    near = u @ u.T >= 0.95
    want = near.sum(axis=1) - 1
    assert (got.n_links.to_numpy()[: len(x)] <= want).all() and got.n_links[: len(x)].sum() >= 0.97 * want.sum()
    assert (got.n_links[len(x) :] == 0).all() and (got.kept == (got.vec_id == got.component_id)).all()
    assert near_vectors.near_vectors(frame(spark, [])).count() == 0


def test_topk_against_brute_force_with_ties(spark):
    rng = np.random.default_rng(4)
    x = np.round(rng.normal(size=(150, 8)) * 2) / 2
    got = topk.threshold_topk(frame(spark, [*x, None, [float("inf")] * 8]), F.col("vec_id") % 10 == 0, 5).toPandas()
    v = np.floor(1024 * x).astype(np.int64)
    for q in range(0, 150, 10):
        s = v @ v[q]
        want = [(int(i), int(s[i])) for i in np.lexsort((np.arange(150), -s)) if i != q][:5]
        mine = got[got.query_id == q].sort_values("rank")
        assert list(zip(mine.vec_id, mine.score, strict=True)) == want


def test_threshold_search_stops_early():
    x = np.arange(4000)[:, None] * np.ones((1, 3), np.int64)
    lists = topk.SortedLists(np.arange(4000), x.astype(np.int64))
    _, scores, seen = lists.top(np.array([1, 2, 3]), 3, None)
    assert scores[0] == 6 * 3999 and seen < 100
    # A score that must be reached closes the block unread.
    assert lists.top(np.array([1, 2, 3]), 3, None, 6 * 4000)[2] == 0
    rows, scores, _ = lists.top(np.array([1, 2, 3]), 3, 3999, 6 * 3998)
    assert rows.tolist() == [3998] and scores.tolist() == [6 * 3998]


def test_topk_over_blocks_shares_the_kth_score(spark, monkeypatch):
    monkeypatch.setattr(topk, "ROW_BLOCK", 100)
    monkeypatch.setattr(topk, "QUERY_BLOCK", 7)
    rng = np.random.default_rng(9)
    # Few components carry most of a product, so the lists of these settle it.
    x = rng.normal(size=(900, 12)) * 0.3 ** np.arange(12)
    x[400:410] = x[0]
    rows = [(i, [float(c) for c in v], "s") for i, v in enumerate(x)] + [(5000, [1.0, 2.0], "s"), (5001, [3.0, 1.0], "s"), (5002, [], "s"), (None, [1.0, 2.0], "s")]
    db = spark.createDataFrame(rows, "vec_id long, embedding array<float>, score string")
    asks = (F.col("vec_id") % 10 == 0) | (F.col("vec_id") == 5001)
    got = topk.threshold_topk(db, asks, 5).toPandas()
    v = np.floor(1024 * x.astype(np.float32).astype(float)).astype(np.int64)
    for q in range(0, 900, 10):
        s = v @ v[q]
        want = [(int(i), int(s[i])) for i in np.lexsort((np.arange(900), -s)) if i != q][:5]
        mine = got[got.query_id == q].sort_values("rank")
        assert list(zip(mine.vec_id, mine.score, strict=True)) == want
    assert got[got.query_id == 5000].vec_id.tolist() == [5001] and got[got.query_id == 5001].score.tolist() == [5 * 1024**2]
    seen = topk.rows_seen(topk.topk_found(db, asks, 5)).toPandas()
    assert seen[seen.query_id < 5000].seen.mean() < 0.6 * 900
    assert topk.threshold_topk(db.where("false"), asks, 5).count() == 0
    assert topk.threshold_topk(db.where("vec_id < 4"), F.lit(True), 50).count() == 4 * 3


def test_near_vectors_of_several_lengths_and_large_buckets(spark, monkeypatch):
    monkeypatch.setattr(near_vectors, "BLOCK", 8)
    rng = np.random.default_rng(5)
    one, two = rng.normal(size=16), rng.normal(size=5)
    x = [*(one + rng.normal(size=(40, 16)) * 0.02), *(two + rng.normal(size=(6, 5)) * 0.01), *rng.normal(size=(20, 16)), [], [2.0]]
    rows = [(i, [float(c) for c in v], "k") for i, v in enumerate(x)] + [(0, [float(c) for c in one], "k"), (None, [float(c) for c in one], "k")]
    got = near_vectors.near_vectors(spark.createDataFrame(rows, "vec_id long, embedding array<float>, key string")).toPandas()
    assert len(got) == len(rows)
    first = got[got.vec_id.between(0, 39)]
    assert (first.n_links == 40).all() and (first.component_id == 0).all()
    second = got[got.vec_id.between(40, 45)]
    assert (second.n_links == 5).all() and (second.component_id == 40).all()
    assert (got[got.vec_id > 45].n_links == 0).all() and got[got.vec_id.isna()].n_links.tolist() == [0]


def test_bounds_hold_the_products():
    rng = np.random.default_rng(1)
    x = rng.normal(size=(400, 64))
    x[200:] = x[:200] + rng.normal(size=(200, 64)) * 0.3
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    coder = near_vectors.Coder(64, 8, 4)
    _, codes, planes, consts = coder.of(x)
    i, j = np.triu_indices(400, 1)
    upper = coder.estimates(codes, planes, consts)(i, j)
    real = np.einsum("ij,ij->i", x[i], x[j])
    assert (upper >= real).mean() > 0.999 and (upper[real < 0.3] < 0.95).mean() > 0.99


def test_operators_equal_their_sql(spark):
    import duckdb

    from vecengine.llm import registry

    con, place = duckdb.connect(), "/root/testdata/sf0.001"
    for t in ("documents", "embeddings"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{place}/{t}.parquet')")
    for name, sql in registry.ORACLE_SQL.items():
        df = registry.QUERIES[name](spark, place)
        got = sorted(tuple(r) for r in df.collect())
        assert got == sorted(con.execute(f"SELECT {', '.join(df.columns)} FROM ({sql})").fetchall()), name


@pytest.mark.parametrize("n", [0, 5, 333])
def test_shards_are_even_and_keep_groups(spark, n):
    texts = [None if i % 50 == 49 else "hot" if i % 3 == 0 else f"t{i // 4}" for i in range(n)]
    d = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "doc_id long, text string")
    got = sharding.balanced_shards(d).toPandas()
    assert len(got) == n
    if n >= 16:
        sizes = got.groupby("shard").size()
        assert sizes.max() - sizes.min() <= 1 and (got.groupby("shard").slot.max() + 1 == sizes).all() and (got.groupby("shard").slot.nunique() == sizes).all()
        assert got[got["size"] == 4].groupby("shard").size().max() >= n // 16 - 1


@pytest.mark.parametrize(("n_groups", "copies", "single", "cut"), [(160, 2, 0, 0), (1, 300, 20, 300 * 299 // 2 - 15 * 190), (7, 40, 40, None)])
def test_shards_cut_few_copies(spark, n_groups, copies, single, cut):
    rows = [(i, f"text {i % n_groups}") for i in range(n_groups * copies)] + [(10_000 + i, f"alone {i}") for i in range(single)]
    got = sharding.balanced_shards(spark.createDataFrame(rows, "doc_id long, text string")).persist()
    edges, lost = sharding.cut_edges(got).first()
    assert got.count() == 320 and got.groupBy("shard").count().where("count <> 20").count() == 0
    assert edges == n_groups * copies * (copies - 1) // 2
    # Groups of 40 fill two shards of 20 each.
    assert lost == (7 * 400 if cut is None else cut)


def test_key_shards_move_rows_into_the_new_one_only(spark):
    d = spark.createDataFrame([(i, f"t{i}") for i in range(400)] + [(None, None)], "doc_id long, text string")
    got = sharding.key_shards(d).toPandas()
    moved = got[got["shard"] != got.grown_shard]
    assert (moved.grown_shard == 16).all() and 5 < len(moved) < 60


def test_components(spark):
    e = spark.createDataFrame([(i, i + 1) for i in range(30)] + [(50, 51), (60, 60)], "a long, b long")
    got = {r["id"]: r["comp"] for r in common.components(e).collect()}
    assert all(got[i] == 0 for i in range(31)) and got[51] == 50 and 60 not in got


def test_shards_of_odd_tables(spark):
    rows = [(None, "same", 1)] * 40 + [(1, None, 1)] * 3 + [(2, "", 1), (3, "x" * 100_000, 1)]
    got = sharding.balanced_shards(spark.createDataFrame(rows, "doc_id long, text string, shard int")).toPandas()
    sizes = got.groupby("shard").size()
    assert len(got) == len(rows) and sizes.max() - sizes.min() <= 1
    assert all(sorted(g.slot) == list(range(len(g))) for _, g in got.groupby("shard")) and got["size"].max() == 100_001
