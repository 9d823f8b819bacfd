"""Pruning, neighbour graphs, and the error theory of pruning from codes."""

from __future__ import annotations

import math

from pyspark.sql import functions as F

from vecengine.functions import quantize
from vecengine.functions.vectors import sq_l2
from vecengine.operators import graph, model, theory
from vecengine.sources import io
from vecengine.workloads import base as B
from vecengine.workloads.base import query

KNN = "knn AS MATERIALIZED (SELECT a.id AS src, b.id AS id, {score} AS score, row_number() OVER (PARTITION BY a.id ORDER BY {score} DESC, b.id) AS rank FROM {s} a, {s} b WHERE a.id <> b.id QUALIFY rank <= {k})"


def knn_sql(k: int, source: str = "db", kind: str = "l2") -> str:
    return KNN.format(score=B.score("a.vec", "b.vec", kind), k=k, s=source)


@query(f"WITH {B.DB}, {knn_sql(10)} SELECT src, CAST(rank AS INTEGER) AS rank, id, round(score, 6) AS score FROM knn")
def knn_graph_exact(spark, sf_dir):
    return graph.knn_candidates(io.base(spark, sf_dir), 10).withColumn("score", F.round("score", 6))


def _prune_sql(alpha: float, degree: int, kind: str, kappa: int = 40) -> str:
    cover = B.score("s.vec", "c.vec", kind)
    return (
        f"WITH {B.DB}, sub AS (SELECT * FROM db), {knn_sql(kappa, 'sub', kind)}, "
        "c AS MATERIALIZED (SELECT src, list({'id': knn.id, 'score': score, 'vec': sub.vec} ORDER BY score DESC, knn.id) AS cands FROM knn JOIN sub ON sub.id = knn.id GROUP BY src), "
        f"k AS (SELECT src, list_reduce(list_concat([cands[1:0]], list_transform(cands, lambda c: [c])), lambda kept, one: "
        f"CASE WHEN len(kept) >= {degree} OR len(list_filter(kept, lambda s: {alpha} * ({cover.replace('c.vec', 'one[1].vec')}) >= one[1].score)) > 0 THEN kept ELSE list_concat(kept, one) END) AS kept FROM c) "
        "SELECT src, CAST(unnest(range(0, len(kept))) AS INTEGER) AS pos, unnest(list_transform(kept, lambda x: x.id)) AS id FROM k"
    )


def _prune(name: str, alpha: float, degree: int, kind: str):
    @query(_prune_sql(alpha, degree, kind), name)
    def run(spark, sf_dir):
        db = io.base(spark, sf_dir)
        return graph.prune(graph.knn_candidates(db, 40, kind), db, alpha, degree, kind)


_prune("prune_neighbors_exact", 1.0, 16, "l2")
_prune("prune_alpha12", 1.2, 16, "l2")
_prune("prune_ip095", 0.95, 16, "ip")


@query(f"WITH {B.DB}, {knn_sql(8)}, r AS (SELECT src, id FROM knn UNION SELECT id AS src, src AS id FROM knn) SELECT src, id FROM r")
def reverse_edges(spark, sf_dir):
    return graph.add_reverse(graph.knn_candidates(io.base(spark, sf_dir), 8).select("src", "id"))


@query(f"WITH {B.DB}, {knn_sql(8)} SELECT src, array_to_string(list(id ORDER BY id), ',') AS nbrs FROM knn GROUP BY src")
def adjacency_lists(spark, sf_dir):
    adj = graph.adjacency(graph.knn_candidates(io.base(spark, sf_dir), 8))
    return adj.select("src", F.concat_ws(",", F.transform("nbrs", lambda n: n.cast("string"))).alias("nbrs"))


TRIPLETS = (
    f"{knn_sql(20)}, t AS (SELECT s.src AS x, s.id AS xs, p.id AS xp FROM knn s JOIN knn p ON s.src = p.src "
    "WHERE s.rank % 5 = s.src % 5 AND p.rank > s.rank AND (p.rank + s.rank + s.src) % 8 = 0)"
)


@query(f"WITH {B.DB}, {TRIPLETS} SELECT x, xs, xp FROM t")
def triplet_sample(spark, sf_dir):
    return theory.triplets(io.base(spark, sf_dir))


@query(
    f"WITH {B.DB}, {TRIPLETS}, w AS (SELECT x, xs, xp, a.vec AS vx, b.vec AS vs, c.vec AS vp FROM t JOIN db a ON a.id = x JOIN db b ON b.id = xs JOIN db c ON c.id = xp) "
    f"SELECT x, xs, xp, CASE WHEN {B.sq_l2('vs', 'vp')} <= {B.sq_l2('vx', 'vp')} THEN 1 ELSE 0 END AS pruned FROM w"
)
def bisector_rule(spark, sf_dir):
    """Which side of the bisector decides; the SQL compares the two distances instead."""
    db = io.base(spark, sf_dir)
    w = theory.with_vectors(theory.triplets(db), db)
    return w.select("x", "xs", "xp", F.when(graph.bisector_margin("vx", "vs", "vp") <= 0, 1).otherwise(0).alias("pruned"))


def _coded_sql(bits: int, kind: str = "pv") -> str:
    enc = (B.pv if kind == "pv" else B.gl)(bits)
    dec = "v AS (SELECT id, vec, step, list_transform(codes, lambda c: lo + step * CAST(c AS DOUBLE)) AS dec FROM enc)"
    return (
        f"{B.MEAN}, {TRIPLETS}, {enc}, {dec}, "
        "w AS (SELECT x, xs, xp, a.vec AS vx, b.vec AS vs, c.vec AS vp, a.dec AS dx, b.dec AS ds, c.dec AS dp, a.step AS step_x, b.step AS step_s, c.step AS step_p "
        "FROM t JOIN v a ON a.id = x JOIN v b ON b.id = xs JOIN v c ON c.id = xp), "
        f"e AS (SELECT x, xs, xp, step_x, step_s, step_p, len(vx) AS d, ({B.sq_l2('vs', 'vp')} - {B.sq_l2('vx', 'vp')}) / 2 AS margin, ({B.sq_l2('ds', 'dp')} - {B.sq_l2('dx', 'dp')}) / 2 AS coded, "
        f"{B.sq_l2('vx', 'vs')} AS xs2, {B.sq_l2('vx', 'vp')} AS xp2, {B.sq_l2('vs', 'vp')} AS sp2 FROM w)"
    )


@query(f"WITH {_coded_sql(4)} SELECT count(*) AS triplets, count(*) FILTER (WHERE abs(coded - margin) < abs(margin) AND (margin <= 0) <> (coded <= 0)) AS violations FROM e")
def prop_equivalence_check(spark, sf_dir):
    """The rule decides alike wherever the error is below the margin: no violation may occur."""
    db = io.base(spark, sf_dir)
    t = theory.coded_triplets(db, theory.triplets(db), 4)
    bad = (F.abs("error") < F.abs("margin")) & ((F.col("margin") <= 0) != (F.col("coded") <= 0))
    return t.agg(F.count("*").alias("triplets"), F.count_if(bad).alias("violations"))


def _moments(bits: int) -> str:
    sx, ss, sp = "step_x * step_x", "step_s * step_s", "step_p * step_p"
    return (
        f"WITH {_coded_sql(bits)}, m AS (SELECT *, coded - margin AS error, d / 24.0::DOUBLE * ({ss} - {sx}) AS mu, "
        f"({sp} * xs2 + {ss} * sp2 + {sx} * xp2) / 12 + d * ({sx} * {sx} + {ss} * {ss}) / 720 + d * {sp} * ({sx} + {ss}) / 144 AS var FROM e)"
    )


@query(f"{_moments(4)} SELECT round(avg((error - mu) / sqrt(var)), 6) AS mean, round(stddev_pop((error - mu) / sqrt(var)), 6) AS std FROM m")
def error_moments(spark, sf_dir):
    """The standardized error: mean about 0 and deviation about 1 if the theory holds."""
    db = io.base(spark, sf_dir)
    m = theory.error_moments(theory.coded_triplets(db, theory.triplets(db), 4))
    z = (F.col("error") - F.col("mu")) / F.sqrt("var")
    return m.agg(F.round(F.avg(z), 6).alias("mean"), F.round(F.stddev_pop(z), 6).alias("std"))


def _erf_sql(x: str) -> str:
    p, a = theory.ERF_P, theory.ERF_A
    t = f"(1 / (1 + {p} * abs({x})))"
    poly = "0.0::DOUBLE"
    for c in reversed(a):
        poly = f"(({poly} + {c}::DOUBLE) * {t})"
    return f"(CASE WHEN {x} < 0 THEN -1 ELSE 1 END * (1 - {poly} * exp(-{x} * {x})))"


@query(
    "WITH g AS (SELECT (l_quantity - 25) / 8 AS mu, l_linenumber / 2.0::DOUBLE AS sigma, count(*) AS n FROM lineitem GROUP BY ALL), "
    f"f AS (SELECT mu, sigma, n, 0.5 * (1 + {_erf_sql(f'(-mu / sigma / {math.sqrt(2)!r}::DOUBLE)')}) AS phi FROM g), "
    f"m AS (SELECT mu, sigma, n, sigma * {math.sqrt(2 / math.pi)!r}::DOUBLE * exp(-mu * mu / (2 * sigma * sigma)) + mu * (1 - 2 * phi) AS mean FROM f) "
    "SELECT mu, sigma, n, round(mean, 6) AS mean, round(mean + 3 * sqrt(greatest(0, mu * mu + sigma * sigma - mean * mean)), 6) AS upper FROM m"
)
def folded_band(spark, sf_dir):
    """Bands for the means and deviations that quantity and number of the order lines give."""
    lines = io.table(spark, sf_dir, "lineitem").select(((F.col("l_quantity") - 25) / 8).alias("mu"), (F.col("l_linenumber") / 2).alias("sigma"))
    g = lines.groupBy("mu", "sigma").agg(F.count("*").alias("n"))
    mean, var = theory.folded_normal(F.col("mu"), F.col("sigma"))
    return g.select("mu", "sigma", "n", F.round(mean, 6).alias("mean"), F.round(mean + 3 * F.sqrt(F.greatest(F.lit(0.0), var)), 6).alias("upper"))


@query(
    f"WITH {B.MEAN}, {B.pv(4)}, r AS (SELECT step, unnest(list_transform(range(1, len(vec) + 1), lambda i: (vec[i] - (lo + step * CAST(codes[i] AS DOUBLE))) / step)) AS u FROM enc WHERE step > 0) "
    "SELECT round(min(u), 6) AS low, round(max(u), 6) AS high, round(avg(u), 6) AS mean, round(var_pop(u) * 12, 6) AS var12, count(*) AS n FROM r"
)
def residual_uniformity(spark, sf_dir):
    """Rounding errors in steps: in [-0.5, 0.5], variance a twelfth (times (d-2)/d, for two components are exact)."""
    db = io.base(spark, sf_dir)
    q = model.centered(db, model.dataset_mean(db)).withColumn("q", quantize.pvq("vec", 4)).where("q.step > 0")
    u = F.explode(F.zip_with("vec", quantize.decode("q"), lambda x, y: (x - y) / F.col("q.step")))
    r = q.select(u.alias("u"))
    return r.agg(F.round(F.min("u"), 6).alias("low"), F.round(F.max("u"), 6).alias("high"), F.round(F.avg("u"), 6).alias("mean"), F.round(F.var_pop("u") * 12, 6).alias("var12"), F.count("*").alias("n"))


def _agreement(bits: int, kind: str) -> str:
    return (
        f"SELECT '{kind}' AS kind, {bits} AS bits, count(*) AS triplets, round(avg(CASE WHEN (margin <= 0) = (coded <= 0) THEN 1.0 ELSE 0.0 END), 6) AS agree, "
        f"round(avg(abs(margin)), 6) AS margin, round(avg(abs(coded - margin)) + 3 * stddev_pop(abs(coded - margin)), 6) AS band FROM (WITH {_coded_sql(bits, kind)} SELECT * FROM e)"
    )


def _agree(spark, sf_dir, cases):
    """A row for each case; triplets and their vectors are found once for all."""
    db = io.base(spark, sf_dir)
    c = theory.coded_margins(db, theory.triplets(db), cases)
    sums, rows = [F.count("*").alias("triplets"), F.round(F.avg(F.abs("margin")), 6).alias("margin")], []
    for i, (kind, bits) in enumerate(cases):
        error = F.abs(F.col(f"coded{i}") - F.col("margin"))
        same = F.when((F.col("margin") <= 0) == (F.col(f"coded{i}") <= 0), 1.0).otherwise(0.0)
        sums += [F.round(F.avg(same), 6).alias(f"agree{i}"), F.round(F.avg(error) + 3 * F.stddev_pop(error), 6).alias(f"band{i}")]
        rows.append(F.struct(F.lit(kind).alias("kind"), F.lit(bits).alias("bits"), "triplets", F.col(f"agree{i}").alias("agree"), "margin", F.col(f"band{i}").alias("band")))
    return c.agg(*sums).select(F.inline(F.array(*rows)))


@query(_agreement(4, "pv"))
def rule_agreement(spark, sf_dir):
    return _agree(spark, sf_dir, [("pv", 4)])


_CASES = [(k, b) for k in ("pv", "gl") for b in (2, 4, 8)]


@query(" UNION ALL ".join(_agreement(b, k) for k, b in _CASES))
def w7_triplets(spark, sf_dir):
    """Safe bit widths: pruning decisions from codes against exact ones."""
    return _agree(spark, sf_dir, _CASES)


@query(f"WITH {B.DB}, {knn_sql(12)}, d AS (SELECT src, count(*) AS degree FROM knn GROUP BY src) SELECT degree, count(*) AS vertices FROM d GROUP BY degree")
def degree_bound(spark, sf_dir):
    return graph.degree_stats(graph.knn_candidates(io.base(spark, sf_dir), 12))


@query(
    f"WITH RECURSIVE {B.MEAN}, {knn_sql(6)}, e0 AS (SELECT id FROM db, mean ORDER BY {B.sq_l2('vec', 'm')}, id LIMIT 1), "
    "r AS (SELECT id FROM e0 UNION SELECT knn.id FROM r JOIN knn ON knn.src = r.id) SELECT id FROM r"
)
def reachable_nodes(spark, sf_dir):
    db = io.base(spark, sf_dir)
    mu = F.array(*(F.lit(m) for m in model.dataset_mean(db)))
    start = db.agg(F.min_by("id", F.struct(sq_l2("vec", mu), F.col("id"))).alias("id")).first()["id"]
    edges = io.staged(graph.knn_candidates(db, 6).select("src", "id"), "edges")
    return graph.reachable(edges, [start]).select("id")
