"""Graph search and its competitors: the experiments, scaled to the given tables."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import functions as F

from vecengine.functions.vectors import dimension, normalize
from vecengine.operators import exact, graph, measures, model, pq, shard
from vecengine.plans import planner
from vecengine.sources import embed, io
from vecengine.workloads import base as B
from vecengine.workloads.base import query


def dealt(db, rows: int = planner.SHARD_ROWS):
    """Shards as the planner deals them; ``rows`` lowers its bound, so that small tables have several too."""
    return planner.deal(db, db.count(), dimension(db), rows)


def outcome(method: str, params: str, found, truth, k: int = 10, vector_bytes: float = 0, degree: int = 0, n: int = 0):
    """One line of an experiment: recall, mean distance evaluations, bytes that a query reads for them, bytes of the index."""
    cost = found.select("qid", "evals").distinct().agg(F.avg("evals").alias("evals")) if "evals" in found.columns else None
    rec = measures.recall(found, truth, k)
    rec = rec.crossJoin(cost) if cost is not None else rec.withColumn("evals", F.lit(float(n)))  # one row each
    return rec.select(F.lit(method).alias("method"), F.lit(params).alias("params"), F.round("recall", 6).alias("recall"), F.round("evals", 3).alias("evals"), F.round(F.col("evals") * vector_bytes, 1).alias("bytes_read"), F.lit(int(n * (vector_bytes + 4 * degree))).alias("bytes"))


def union(parts):
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def bytes_of(codec: str, d: int, pad: int = 32) -> int:
    if codec[:2] == "pq":
        return int(codec[2:])
    if codec in ("f32", "f16"):
        return d * (4 if codec == "f32" else 2)
    bits = [int(b) for b in codec[2:].split("x")]
    first = math.ceil((d * bits[0] + (32 if codec[:2] == "pv" else 0)) / 8 / pad) * pad
    return first + (math.ceil(d * bits[1] / 8) if len(bits) == 2 else 0)


#: Fixed value: the loss threshold of the score-aware codes.
LOSS = 0.2


def setting(spark, sf_dir, kind: str = "l2", k: int = 10, db=None, q=None):
    db = io.base(spark, sf_dir) if db is None else db
    q = io.held_out(spark, sf_dir) if q is None else q
    return db, q, io.staged(exact.exact_knn(db, q, k, kind), "truth"), db.count()


@query()
def graph_search_beam(spark, sf_dir):
    """8-bit codes in graph and search, window 40."""
    db, q, *_ = setting(spark, sf_dir)
    index = shard.build_index(dealt(db), "pv8", 16, 32)
    return shard.search_index(index, q, 10, 40).withColumn("score", F.round("score", 6))


@query(f"WITH {B.DB} SELECT qid, CAST(rank AS INTEGER) AS rank, id, round(score, 5) AS score FROM ({B.knn()})")
def graph_search_full_beam(spark, sf_dir):
    """With a window of all rows on a connected graph the search is exact."""
    db, q, _, n = setting(spark, sf_dir)
    index = shard.build_index(dealt(db), "f32", 16, 32)
    return shard.search_index(index, q, 10, n).select("qid", "rank", "id", F.round("score", 5).alias("score"))


@query()
def beam_sweep(spark, sf_dir):
    """Recall and cost as the window grows; with and without the visited set."""
    db, q, truth, n = setting(spark, sf_dir)
    index = io.staged(shard.build_index(dealt(db), "pv8", 16, 32), "index")
    return union([outcome("visited" if v else "beam", f"W={w}", shard.search_index(index, q, 10, w, visited=v), truth, 10, bytes_of("pv8", 64), 16, n) for w in (10, 20, 40, 80) for v in (False, True)])


@query()
def graph_search_rounds(spark, sf_dir):
    """One global graph, searched round by round as DataFrames."""
    db, q = model.encode(io.base(spark, sf_dir), "pv8"), io.held_out(spark, sf_dir)
    db = io.staged(db, "decoded")
    cands = graph.knn_candidates(db, 24)
    edges = io.staged(graph.add_reverse(graph.prune(cands, db, 1.2, 8).select("src", "id")), "edges")
    start = int(db.agg(F.min("id")).first()[0])
    return graph.graph_search_rounds(edges, db, q, 5, 10, [start]).withColumn("score", F.round("score", 6))


@query()
def graph_rerank(spark, sf_dir):
    """Two-level codes: search on the first level, final beam by both."""
    db, q, truth, n = setting(spark, sf_dir)
    parts, codecs = [], ("pv4x4", "pv4x8", "pv8x8")
    built = io.staged_together([shard.build_index(dealt(db), codec, 16, 32) for codec in codecs], "index")
    for codec, index in zip(codecs, built, strict=True):
        parts += [outcome(codec, f"rerank={r}", shard.search_index(index, q, 10, 40, rerank=r), truth, 10, bytes_of(codec, 64), 16, n) for r in (False, True)]
    return union(parts)


@query()
def build_from_codes(spark, sf_dir):
    """Edges shared by the graph built from 8-bit codes and the one built from floats, and both degrees."""
    db = io.base(spark, sf_dir)
    mean = model.dataset_mean(db)
    coded, plain = (shard.edges_of(shard.build_index(dealt(db), c, 16, 32, mean=mean, search_codec="f32")).select("src", "id") for c in ("pv8", "f32"))
    both = coded.withColumn("coded", F.lit(1)).join(plain.withColumn("plain", F.lit(1)), ["src", "id"], "full")
    return both.agg(F.count("coded").alias("coded"), F.count("plain").alias("plain"), F.count_if(F.col("coded").isNotNull() & F.col("plain").isNotNull()).alias("shared"))


@query()
def w5_build_bits(spark, sf_dir):
    """Graphs built from codes of few bits, searched in full precision."""
    db, q, truth, n = setting(spark, sf_dir)
    mean = model.dataset_mean(db)
    parts = []
    for codec in ("f32", "pv8", "pv4", "pv2", "gl4", "gl2"):
        index = io.staged(shard.build_index(dealt(db), codec, 16, 32, mean=mean, search_codec="f32"), "index")
        parts += [outcome(f"built {codec}", f"W={w}", shard.search_index(index, q, 10, w), truth, 10, 256, 16, n) for w in (20, 40)]
    return union(parts)


def _competitors(db, q, truth, n, d: int, kind: str, k: int, degree: int, windows):
    alphas = (1.0, 0.95) if kind == "ip" else (1.0, 1.2)
    parts = []
    for codec in ("pv8", "pv4x4", "pv4x8", "pv8x8", "f32", "f16", f"pq{max(4, d // 2)}"):
        index = io.staged(shard.build_index(dealt(db), codec, degree, 2 * degree, alphas, kind), "index")
        for w in windows:
            parts.append(outcome(codec, f"R={degree},W={w}", shard.search_index(index, q, k, w, rerank="x" in codec), truth, k, bytes_of(codec, d), degree, n))
    layers = io.staged(shard.search_layers(dealt(db), q, k, tuple(windows), degree, 200, kind), "layers")
    parts += [outcome("layered", f"M={degree // 2},W={w}", layers.where(F.col("window") == w).drop("window"), truth, k, 4 * d, degree, n) for w in windows]
    local = io.staged(shard.build_index(dealt(db), "f32", degree, 2 * degree, alphas, kind, search_codec="pv4"), "index")
    for w in windows:
        again = pq.rerank(shard.search_index(local, q, w, w, carry=True, batch=1), db, q, k, kind)
        parts.append(outcome("coded neighbourhoods", f"R={degree},W={w}", again, truth, k, degree * bytes_of("pv4", d, 1), degree, n))
    x = pq.sample(db)
    cells = max(2, int(math.sqrt(n)))
    code = pq.train(x, max(4, d // 4), 16)
    coarse = pq.ivf_build(db, max(4, n // 64), code)
    tree = pq.ivf_build(db, cells, pq.train(x, -(-d // 2), 16, eta=max(1.0, pq.score_aware_eta(LOSS, d))))
    for probe in (2, 8):
        parts.append(outcome("inverted file", f"nprobe={probe},rerank=100", pq.rerank(pq.ivf_search(coarse, q, 100, probe, kind), db, q, k, kind), truth, k, code.segments, 0, n))
        parts.append(outcome("partition tree", f"leaves={probe},reorder=60", pq.rerank(pq.ivf_search(tree, q, 60, probe, kind), db, q, k, kind), truth, k, -(-d // 2), 0, n))
    return parts


@query()
def w1_small(spark, sf_dir):
    """All methods by distance on prefixes of 25 and 50 dimensions and the whole 64, degree 16, windows 20 and 40."""
    parts = []
    for d in (25, 50, 64):
        db, q, truth, n = setting(spark, sf_dir, "l2", 10, *prefixes(spark, sf_dir, d))
        parts += [p.withColumn("data", F.lit(f"V{d}")) for p in _competitors(db, q, truth, n, d, "l2", 10, 16, (20, 40))]
    return union(parts)


def prefixes(spark, sf_dir, d: int):
    v = io.vectors(spark, sf_dir).select("id", F.slice("vec", 1, d).alias("vec")).select("id", normalize("vec").alias("vec"))
    v = io.staged(v, "prefixes")
    return v.where("id % 10 <> 0"), v.where("id % 10 = 0").withColumnRenamed("id", "qid")


@query()
def w2_large(spark, sf_dir):
    """Inner product on vectors of different norms in several shards, k 10, 50 and 100, with the inverted file and the partition tree beside the graph."""
    v = io.vectors(spark, sf_dir).select("id", F.transform("vec", lambda x: x * (1 + F.col("label") / 10)).alias("vec"))
    db, q = v.where("id % 10 <> 0"), v.where("id % 10 = 0").withColumnRenamed("id", "qid")
    db, q, truth, n = setting(spark, sf_dir, "ip", 100, io.staged(db, "norms"), q)
    shards = max(250, n // 4)
    parts = []
    codecs, mean = ("pv8", "pv4x4", "f32"), model.dataset_mean(db)
    built = io.staged_together([shard.build_index(dealt(db, shards), codec, 32, 64, (1.0, 0.95), "ip", mean=mean) for codec in codecs], "index")
    for codec, index in zip(codecs, built, strict=True):
        for k, w in ((10, 20), (10, 40), (10, 80), (50, 80), (100, 160)):
            parts.append(outcome(codec, f"R=32,W={w},k={k}", shard.search_index(index, q, k, w, rerank="x" in codec), truth, k, bytes_of(codec, 64), 32, n))
    x = pq.sample(db)
    coarse = pq.ivf_build(db, max(4, n // 64), pq.train(x, 16, 16))
    tree = pq.ivf_build(db, max(2, int(math.sqrt(n))), pq.train(x, 32, 16, eta=max(1.0, pq.score_aware_eta(LOSS, 64))))
    for method, index, size in (("inverted file", coarse, 16), ("partition tree", tree, 32)):
        parts += [outcome(method, f"nprobe={p},rerank=100", pq.rerank(pq.ivf_search(index, q, 100, p, "ip"), db, q, 10, "ip"), truth, 10, size, 0, n) for p in (2, 8)]
    return union(parts)


@query()
def w3_memory(spark, sf_dir):
    """Bytes of the index against recall and bytes read, three degrees, several shards; the inverted file beside them."""
    db, q, truth, n = setting(spark, sf_dir)
    parts = []
    mean, shards = model.dataset_mean(db), max(250, n // 4)
    cases = [(degree, codec) for degree in (8, 16, 32) for codec in ("pv8", "pv4x8", "f32")]
    built = io.staged_together([shard.build_index(dealt(db, shards), codec, degree, 2 * degree, mean=mean) for degree, codec in cases], "index")
    for (degree, codec), index in zip(cases, built, strict=True):
        parts.append(outcome(codec, f"R={degree},W=40", shard.search_index(index, q, 10, 40, rerank="x" in codec), truth, 10, bytes_of(codec, 64), degree, n))
    coarse = pq.ivf_build(db, max(4, n // 64), pq.train(pq.sample(db), 32, 16))
    parts += [outcome("inverted file", f"nprobe={p},rerank=100", pq.rerank(pq.ivf_search(coarse, q, 100, p), db, q, 10), truth, 10, 32, 0, n) for p in (1, 2, 4, 8)]
    return union(parts)


@query()
def w4_ivf(spark, sf_dir):
    """The grid of the inverted file: cells, segments, cells probed, rows re-ranked."""
    db, q, truth, n = setting(spark, sf_dir)
    x, parts = pq.sample(db), []
    for nlist in (8, 16, 32):
        for segments in (16, 32, 64):
            index = pq.ivf_build(db, nlist, pq.train(x, segments, 16))
            for probe in (1, 4, nlist):
                for again in (0, 100):
                    found = pq.ivf_search(index, q, max(10, again), probe)
                    found = pq.rerank(found, db, q, 10) if again else found
                    parts.append(outcome("inverted file", f"nlist={nlist},segments={segments},nprobe={probe},rerank={again}", found, truth, 10, segments, 0, n))
    return union(parts)


@query()
def w10_quantizers(spark, sf_dir):
    """Quantizers under one and the same search."""
    db, q, truth, n = setting(spark, sf_dir)
    parts = []
    for codec in ("f32", "pv8", "pv4x4", "pv4x8", "gl8", "gl4", "gl4x4"):
        index = io.staged(shard.build_index(dealt(db), codec, 16, 32), "index")
        parts.append(outcome(codec, "R=16,W=40", shard.search_index(index, q, 10, 40, rerank="x" in codec), truth, 10, bytes_of(codec, 64), 16, n))
    # One component a segment: distances in the graph are look-ups.
    index = io.staged(shard.build_index(dealt(db), "f32", 16, 32, search_codec="pq64"), "index")
    parts.append(outcome("pq64", "R=16,W=40", shard.search_index(index, q, 10, 40), truth, 10, 64, 16, n))
    return union(parts)


@query()
def pq_scan(spark, sf_dir):
    """Exhaustive scans: product quantization, with rotation, and after reduction of the dimension."""
    db, q, truth, n = setting(spark, sf_dir)
    x, parts = pq.sample(db), []
    for m in (8, 16, 32):
        for rotate in (0, 4):
            code = pq.train(x, m, 16, rotate)
            parts.append(outcome("opq" if rotate else "pq", f"segments={m}", pq.scan(pq.encode_frame(db, code), code, q, 10), truth, 10, m, 0, n))
    mean, axes = pq.pca(x, 32)
    code = pq.train(x, 16, 16)
    parts.append(outcome("pq+rerank", "segments=16,k=100", pq.rerank(pq.scan(pq.encode_frame(db, code), code, q, 100), db, q, 10), truth, 10, 16, 0, n))
    a = F.array(*(F.array(*(F.lit(float(v)) for v in col)) for col in axes.T))
    turned = lambda df, key: df.select(key, F.transform(a, lambda axis: F.aggregate(F.zip_with("vec", axis, lambda u, v: u * v), F.lit(0.0), lambda s, v: s + v)).alias("vec"))
    parts.append(outcome("reduced", "d=32", exact.exact_knn(turned(db, "id"), turned(q, "qid"), 10), truth, 10, 128, 0, n))
    return union(parts)


@query()
def pq_rerank_knn(spark, sf_dir):
    db, q, *_ = setting(spark, sf_dir)
    code = pq.train(pq.sample(db), 16, 16)
    return pq.rerank(pq.scan(pq.encode_frame(db, code), code, q, 100), db, q, 10).withColumn("score", F.round("score", 6))


@query(f"WITH {B.DB} SELECT qid, CAST(rank AS INTEGER) AS rank, id, round(score * score, 5) AS far FROM ({B.knn()})")
def ivf_flat_all_probe(spark, sf_dir):
    """All cells probed, nothing coded: exact."""
    db, q = io.base(spark, sf_dir), io.held_out(spark, sf_dir)
    return pq.ivf_search(pq.ivf_build(db, 8), q, 10, 8).select("qid", "rank", "id", F.round(-F.col("score"), 5).alias("far"))


_BOOK = "book AS (SELECT s, c, [sin(s * 7 + c * 3) / 5, cos(s * 5 + c) / 5] AS v FROM range(0, 32) a(s), range(0, 16) b(c))"


@query(f"WITH {B.DB}, {_BOOK} SELECT id, CAST(s AS INTEGER) AS s, CAST(arg_min(c, (vec[2 * s + 1] - v[1]) * (vec[2 * s + 1] - v[1]) + (vec[2 * s + 2] - v[2]) * (vec[2 * s + 2] - v[2])) AS INTEGER) AS c FROM db, book GROUP BY id, s")
def pq_assign(spark, sf_dir):
    """Codes by a codebook that both engines can make up."""
    book = np.array([[[math.sin(s * 7 + c * 3) / 5, math.cos(s * 5 + c) / 5] for c in range(16)] for s in range(32)])
    coded = pq.encode_frame(io.base(spark, sf_dir), pq.Pq(book))
    text = F.hex("code")
    return coded.select("id", F.posexplode(F.transform(F.sequence(F.lit(0), F.lit(31)), lambda s: F.conv(F.substring(text, s * 2 + 1, 2), 16, 10).cast("int"))).alias("s", "c"))


@query()
def layered_search(spark, sf_dir):
    """The hierarchy of graphs against the flat one, and the graph whose neighbour lists carry 4-bit codes."""
    db, q, truth, n = setting(spark, sf_dir)
    kinds = (("f32", "flat"), ("pv4", "coded neighbourhoods"))
    layers, *built = io.staged_together([shard.search_layers(dealt(db), q, 10, (20, 40), 16, 200), *(shard.build_index(dealt(db), "f32", 16, 32, search_codec=codec) for codec, _ in kinds)], "index")
    parts = [outcome("layered", f"M=8,W={w}", layers.where(F.col("window") == w).drop("window"), truth, 10, 256, 17, n) for w in (20, 40)]
    for (codec, name), index in zip(kinds, built, strict=True):
        found = shard.search_index(index, q, 40 if codec == "pv4" else 10, 40, carry=codec == "pv4", batch=1 if codec == "pv4" else shard.QUERY_BATCH)
        cost = found.select("qid", "evals").distinct()
        again = pq.rerank(found, db, q, 10).join(cost, "qid") if codec == "pv4" else found
        parts.append(outcome(name, "R=16,W=40", again, truth, 10, 256, 16, n))
    return union(parts)


@query()
def sharded_search(spark, sf_dir):
    """Four shards searched apart and merged."""
    db, q, truth, n = setting(spark, sf_dir)
    index = shard.build_index(db.withColumn("shard", F.col("id") % 4), "pv8", 16, 32, mean=model.dataset_mean(db))
    return outcome("pv8", "shards=4,W=20", shard.search_index(index, q, 10, 20), truth, 10, bytes_of("pv8", 64), 16, n)


@query()
def graph_stats(spark, sf_dir):
    """Degrees of a built graph, and that all vertices are reached."""
    db = io.base(spark, sf_dir)
    index = io.staged(shard.build_index(dealt(db), "pv8", 16, 32), "index")
    return graph.degree_stats(shard.edges_of(index)).orderBy("degree")


@query()
def choose_window(spark, sf_dir):
    """The smallest window whose recall on a validation sample reaches the target."""
    db, q, truth, _ = setting(spark, sf_dir)
    index = io.staged(shard.build_index(dealt(db), "pv8", 16, 32), "index")
    return planner.choose_window(index, q, truth, 0.9)


@query()
def w17_passages(spark, sf_dir):
    """Texts as base, user turns and benchmark questions as queries, inner product, 768 dimensions."""
    docs = embed.hash_embed(io.table(spark, sf_dir, "documents"), 768, "doc_id", "text")
    asks = io.table(spark, sf_dir, "conversations").where("role = 'user'").select((F.col("conv_id") * 1000 + F.col("turn")).alias("k"), "text")
    asks = asks.union(io.table(spark, sf_dir, "benchmark").select(-1 - F.col("item_id"), "text"))
    asks = embed.hash_embed(asks, 768, "k", "text").withColumnRenamed("id", "qid")
    db, q, truth, n = setting(spark, sf_dir, "ip", 10, io.staged(docs, "docs"), io.staged(asks, "asks"))
    parts = []
    for codec in ("pv8", "pv4x8", "f32"):
        index = io.staged(shard.build_index(dealt(db), codec, 16, 32, (1.0, 0.95), "ip"), "index")
        parts.append(outcome(codec, "R=16,W=60", shard.search_index(index, q, 10, 60, rerank="x" in codec), truth, 10, bytes_of(codec, 768), 16, n))
    return union(parts)


@query()
def w12_dimensions(spark, sf_dir):
    """Prefixes of the vectors and hashed texts: how dimension and codec move recall, bytes and bytes read. Times are in bench.py."""
    parts = []
    for d in (25, 50, 64, 96, 128):
        if d <= 64:
            db, q = prefixes(spark, sf_dir, d)
        else:
            v = io.staged(embed.hash_embed(io.table(spark, sf_dir, "documents"), d, "doc_id", "text"), "texts")
            db, q = v.where("id % 10 <> 0"), v.where("id % 10 = 0").withColumnRenamed("id", "qid")
        db, q, truth, n = setting(spark, sf_dir, "l2", 10, db, q)
        for codec in ("pv8", "f32"):
            index = io.staged(shard.build_index(dealt(db), codec, 16, 32), "index")
            parts.append(outcome(codec, f"d={d},W=40", shard.search_index(index, q, 10, 40), truth, 10, bytes_of(codec, d), 16, n))
    return union(parts)
