"""Relational operators, each in a role that vector search has for it."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from vecengine.functions import quantize
from vecengine.functions.vectors import norm, sim, sq_l2
from vecengine.operators import exact, measures, model
from vecengine.sources import io
from vecengine.workloads import base as B
from vecengine.workloads.base import query

KNN = f"{B.DB}, k AS ({B.knn()})"


def found(spark: SparkSession, sf_dir: str, k: int = 10, db: DataFrame | None = None) -> DataFrame:
    return exact.exact_knn(io.base(spark, sf_dir) if db is None else db, io.held_out(spark, sf_dir), k)


def approx(spark: SparkSession, sf_dir: str, codec: str = "pv4", k: int = 10) -> DataFrame:
    return found(spark, sf_dir, k, model.encode(io.base(spark, sf_dir), codec))


APPROX = f"{B.MEAN}, {B.codec_sql('pv4')}, k AS ({B.knn()}), a AS ({B.knn('dec')})"


def labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    return io.vectors(spark, sf_dir).select("id", "label")


@query("SELECT vec_id AS id, label FROM embeddings WHERE label IN (1, 3) AND vec_id BETWEEN 100 AND 400")
def scan_embeddings(spark, sf_dir):
    return io.table(spark, sf_dir, "embeddings").where("label IN (1, 3) AND vec_id BETWEEN 100 AND 400").select(F.col("vec_id").alias("id"), "label")


@query(f"WITH {B.EMB}, db AS (SELECT id, vec FROM emb WHERE id % 10 <> 0 AND label = 3), q AS (SELECT id AS qid, vec FROM emb WHERE id % 10 = 0) SELECT qid, CAST(rank AS INTEGER) AS rank, id FROM ({B.knn()})")
def filtered_knn_label(spark, sf_dir):
    """Filter first: the scan reads rows of the label only."""
    db = io.vectors(spark, sf_dir).where("id % 10 <> 0 AND label = 3").select("id", "vec")
    return found(spark, sf_dir, 10, db).select("qid", "rank", "id")


@query(f"WITH {B.DB}, k AS ({B.knn(k=60)}) SELECT qid, CAST(row_number() OVER (PARTITION BY qid ORDER BY k.rank) AS INTEGER) AS rank, k.id FROM k JOIN emb ON emb.id = k.id WHERE label = 3 QUALIFY row_number() OVER (PARTITION BY qid ORDER BY k.rank) <= 10")
def post_filter_knn(spark, sf_dir):
    """Over-fetch, then filter."""
    hits = found(spark, sf_dir, 60).join(labels(spark, sf_dir).where("label = 3"), "id")
    return exact.topk(hits.drop("rank"), 10).select("qid", "rank", "id")


@query(f"WITH {KNN} SELECT qid, k.id, CAST(k.rank AS INTEGER) AS rank, label FROM k JOIN emb ON emb.id = k.id")
def join_result_labels(spark, sf_dir):
    return found(spark, sf_dir).join(labels(spark, sf_dir), "id").select("qid", "id", "rank", "label")


@query("SELECT source, lang, count(*) AS n, CAST(sum(quality) AS BIGINT) AS good, CAST(sum(toxic) AS BIGINT) AS toxic FROM documents d JOIN labels l ON d.doc_id = l.doc_id GROUP BY source, lang")
def doc_quality_join(spark, sf_dir):
    d = io.table(spark, sf_dir, "documents").select("doc_id", "source", "lang")
    both = d.join(io.table(spark, sf_dir, "labels"), "doc_id")
    return both.groupBy("source", "lang").agg(F.count("*").alias("n"), F.sum("quality").alias("good"), F.sum("toxic").alias("toxic"))


@query(f"WITH {KNN} SELECT qid, CAST(rank AS INTEGER) AS rank, id, round(score, 6) AS score FROM k")
def broadcast_query_knn(spark, sf_dir):
    """The queries go to all tasks, whose rows are scored in blocks."""
    return found(spark, sf_dir).withColumn("score", F.round("score", 6))


@query(f"WITH {B.DB} SELECT a.id AS a, b.id AS b FROM db a JOIN db b ON a.id < b.id AND {B.sq_l2('a.vec', 'b.vec')} <= 0.9")
def epsilon_self_join(spark, sf_dir):
    """Pairs within a distance, through the first components: they differ by at most the bound too.

    Cells of that width on the first component; neighbours are in the same or the next cell.
    """
    eps2, width = 0.9, 0.9**0.5
    db = io.base(spark, sf_dir).withColumn("cell", F.floor(F.col("vec")[0] / width))
    left = db.select(F.col("id").alias("a"), F.col("vec").alias("va"), F.explode(F.array(F.col("cell") - 1, F.col("cell"), F.col("cell") + 1)).alias("cell"))
    right = db.select(F.col("id").alias("b"), F.col("vec").alias("vb"), "cell")
    return left.join(right, "cell").where((F.col("a") < F.col("b")) & (sq_l2("va", "vb") <= eps2)).select("a", "b")


IP = "ip AS (SELECT vec_id AS id, label, sqrt(list_reduce(list_transform(embedding, lambda x: (x::DOUBLE * (1 + label / 10.0::DOUBLE)) * (x::DOUBLE * (1 + label / 10.0::DOUBLE))), lambda s, x: s + x)) AS n FROM embeddings)"


def _norms(spark, sf_dir):
    return io.vectors(spark, sf_dir).select("id", "label", norm(F.transform("vec", lambda x: x * (1 + F.col("label") / 10))).alias("n"))


@query(f"WITH {IP} SELECT a.id AS a, b.id AS b FROM ip a JOIN ip b ON b.n BETWEEN a.n - 0.05 AND a.n + 0.05 WHERE a.id <> b.id")
def range_join_norm(spark, sf_dir):
    """Rows whose norm is close, by buckets of the norm."""
    w, rows = 0.05, _norms(spark, sf_dir)
    left = rows.select(F.col("id").alias("a"), F.col("n").alias("na"), F.explode(F.sequence(F.floor(F.col("n") / w) - 1, F.floor(F.col("n") / w) + 1)).alias("cell"))
    right = rows.select(F.col("id").alias("b"), F.col("n").alias("nb"), F.floor(F.col("n") / w).alias("cell"))
    return left.join(right, "cell").where((F.col("nb") >= F.col("na") - w) & (F.col("nb") <= F.col("na") + w) & (F.col("a") != F.col("b"))).select("a", "b")


@query(
    "WITH s AS (SELECT event_id AS a, user_id, ts FROM events WHERE event_type = 'signup'), p AS (SELECT event_id AS b, user_id, ts AS bought FROM events WHERE event_type = 'purchase') "
    "SELECT a, b FROM s JOIN p USING (user_id) WHERE bought BETWEEN ts AND ts + INTERVAL 6 HOUR"
)
def interval_join_events(spark, sf_dir):
    """Purchases within six hours of a sign-up of the same user, by six-hour buckets."""
    e = io.table(spark, sf_dir, "events").select("event_id", "user_id", "event_type", F.unix_micros(F.col("ts").cast("timestamp")).alias("t"))
    w = 6 * 3_600_000_000
    s = e.where("event_type = 'signup'").select(F.col("event_id").alias("a"), "user_id", F.col("t").alias("from"), F.explode(F.array(F.floor(F.col("t") / w), F.floor(F.col("t") / w) + 1)).alias("cell"))
    p = e.where("event_type = 'purchase'").select(F.col("event_id").alias("b"), "user_id", F.col("t").alias("at"), F.floor(F.col("t") / w).alias("cell"))
    return s.join(p, ["user_id", "cell"]).where((F.col("at") >= F.col("from")) & (F.col("at") <= F.col("from") + w)).select("a", "b")


@query(
    "WITH p AS (SELECT event_id, user_id, ts FROM events WHERE event_type = 'purchase'), c AS (SELECT event_id AS click, user_id, ts FROM events WHERE event_type = 'click') "
    "SELECT p.event_id, coalesce(c.click, -1) AS click FROM p ASOF LEFT JOIN c ON p.user_id = c.user_id AND p.ts >= c.ts"
)
def asof_last_event(spark, sf_dir):
    """The user's last click at or before each purchase: one sort for each user, no pairs."""
    e = io.table(spark, sf_dir, "events").where("event_type IN ('purchase', 'click')").select("event_id", "user_id", "ts", "event_type")
    w = Window.partitionBy("user_id").orderBy("ts", F.when(F.col("event_type") == "click", 0).otherwise(1)).rowsBetween(Window.unboundedPreceding, 0)
    last = F.last(F.when(F.col("event_type") == "click", F.col("event_id")), ignorenulls=True).over(w)
    return e.withColumn("click", last).where("event_type = 'purchase'").select("event_id", F.coalesce("click", F.lit(-1)).alias("click"))


@query(f"WITH {APPROX} SELECT a.qid, count(*) AS hits FROM a SEMI JOIN k ON a.qid = k.qid AND a.id = k.id GROUP BY a.qid")
def recall_semi(spark, sf_dir):
    return approx(spark, sf_dir).join(found(spark, sf_dir), ["qid", "id"], "left_semi").groupBy("qid").agg(F.count("*").alias("hits"))


@query(f"WITH {B.EMB}, db AS (SELECT id, vec FROM emb ANTI JOIN (SELECT DISTINCT user_id FROM events WHERE event_type = 'error') d ON emb.id = d.user_id WHERE id % 10 <> 0), q AS (SELECT id AS qid, vec FROM emb WHERE id % 10 = 0) SELECT qid, CAST(rank AS INTEGER) AS rank, id FROM ({B.knn()})")
def deleted_anti(spark, sf_dir):
    """Search without deleted ids."""
    gone = io.table(spark, sf_dir, "events").where("event_type = 'error'").select(F.col("user_id").alias("id")).distinct()
    return found(spark, sf_dir, 10, io.base(spark, sf_dir).join(gone, "id", "left_anti")).select("qid", "rank", "id")


@query(f"WITH {B.DB}, k AS (SELECT * FROM ({B.knn(k=1)}) WHERE score > -1.15) SELECT q.qid, coalesce(k.id, -1) AS id, CASE WHEN k.id IS NULL THEN 0 ELSE 1 END AS hit FROM q LEFT JOIN k ON q.qid = k.qid")
def knn_left_missing(spark, sf_dir):
    near = found(spark, sf_dir, 1).where("score > -1.15").select("qid", "id")
    return io.held_out(spark, sf_dir).select("qid").join(near, "qid", "left").select("qid", F.coalesce("id", F.lit(-1)).alias("id"), F.when(F.col("id").isNull(), 0).otherwise(1).alias("hit"))


@query(f"WITH {B.DB} SELECT q.qid, l.id, round(l.score, 6) AS score FROM q, LATERAL (SELECT db.id, {B.score('q.vec', 'db.vec')} AS score FROM db ORDER BY score DESC, db.id LIMIT 3) l")
def lateral_knn(spark, sf_dir):
    io.base(spark, sf_dir).createOrReplaceTempView("ve_db")
    io.held_out(spark, sf_dir).createOrReplaceTempView("ve_q")
    s = "-sqrt(aggregate(zip_with(q.vec, d.vec, (x, y) -> (x - y) * (x - y)), 0D, (s, x) -> s + x))"
    return spark.sql(f"SELECT q.qid, l.id, round(l.score, 6) AS score FROM ve_q q, LATERAL (SELECT d.id, {s} AS score FROM ve_db d ORDER BY score DESC, d.id LIMIT 3) l")


CENTROIDS = (
    "cells AS (SELECT label, unnest(range(0, len(vec))) AS j, unnest(vec) AS x FROM emb), "
    "cent AS (SELECT label, list(mu ORDER BY j) AS c FROM (SELECT label, j, round(CAST(sum(CAST(x AS DECIMAL(38,15))) AS DOUBLE) / count(*), 12) AS mu FROM cells GROUP BY label, j) GROUP BY label)"
)


def _centroids(spark, sf_dir):
    cells = io.vectors(spark, sf_dir).select("label", F.posexplode("vec").alias("j", "x"))
    mu = cells.groupBy("label", "j").agg(F.round(F.sum(F.col("x").cast("decimal(38,15)")).cast("double") / F.count("*"), 12).alias("mu"))
    return mu.groupBy("label").agg(F.transform(F.array_sort(F.collect_list(F.struct("j", "mu"))), lambda s: s["mu"]).alias("c"))


@query(f"WITH {B.EMB}, {CENTROIDS} SELECT label, CAST(unnest(range(0, len(c))) AS INTEGER) AS j, round(unnest(c), 9) AS x FROM cent")
def label_centroids(spark, sf_dir):
    return _centroids(spark, sf_dir).select("label", F.posexplode("c").alias("j", "x")).withColumn("x", F.round("x", 9))


@query(f"WITH {B.EMB}, {CENTROIDS} SELECT id, arg_min(cent.label, {B.sq_l2('vec', 'c')}) AS cell FROM emb, cent GROUP BY id")
def assign_cells(spark, sf_dir):
    cent = _centroids(spark, sf_dir).withColumnRenamed("label", "cell")  # as many rows as labels
    pairs = io.vectors(spark, sf_dir).select("id", "vec").crossJoin(F.broadcast(cent))
    return pairs.groupBy("id").agg(F.min_by("cell", sq_l2("vec", "c")).alias("cell"))


@query(f"WITH {KNN}, n AS (SELECT a.qid, b.id AS far FROM k a JOIN k b ON a.id = b.id) SELECT qid, count(DISTINCT far) AS reached, count(*) AS scored FROM n GROUP BY qid")
def distinct_reached(spark, sf_dir):
    k = found(spark, sf_dir)
    pairs = k.select("qid", "id").join(k.select("id", F.col("id").alias("far")), "id")
    return pairs.groupBy("qid").agg(F.countDistinct("far").alias("reached"), F.count("*").alias("scored"))


CODECS = ("pv2", "pv4", "pv8", "gl2", "gl4", "gl8")


def _report_sql(select: str) -> str:
    ctes = ", ".join(B.codec_sql(c, f"d_{c}") for c in CODECS)
    lists = ", ".join(f"a_{c} AS MATERIALIZED ({B.knn(f'd_{c}')})" for c in CODECS)
    rows = " UNION ALL ".join(f"SELECT '{c[:2]}' AS method, {c[2]} AS bits, k.qid, CASE WHEN a.id IS NULL THEN 0 ELSE 1 END AS hit FROM k LEFT JOIN a_{c} a ON a.qid = k.qid AND a.id = k.id" for c in CODECS)
    return f"WITH {B.MEAN}, k AS MATERIALIZED ({B.knn()}), {ctes}, {lists}, r AS MATERIALIZED ({rows}) {select}"


def results(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(method, bits, qid, hit) of every codec."""
    truth, db = io.staged(found(spark, sf_dir).select("qid", "id"), "truth"), io.base(spark, sf_dir)
    mean, out = model.dataset_mean(db), None
    for codec in CODECS:
        got = found(spark, sf_dir, 10, model.encode(db, codec, mean)).select("qid", "id", F.lit(1).alias("hit"))
        one = truth.join(got, ["qid", "id"], "left").select(F.lit(codec[:2]).alias("method"), F.lit(int(codec[2:])).alias("bits"), "qid", F.coalesce("hit", F.lit(0)).alias("hit"))
        out = one if out is None else out.unionByName(one)
    return out


@query(_report_sql("SELECT coalesce(method, 'all') AS method, coalesce(bits, 0) AS bits, count(*) AS n, round(avg(hit), 6) AS recall FROM r GROUP BY CUBE (method, bits)"))
def report_cube(spark, sf_dir):
    return results(spark, sf_dir).cube("method", "bits").agg(F.count("*").alias("n"), F.round(F.avg("hit"), 6).alias("recall")).fillna({"method": "all", "bits": 0})


@query(_report_sql("SELECT coalesce(method, 'all') AS method, coalesce(bits, 0) AS bits, count(*) AS n, round(avg(hit), 6) AS recall FROM r GROUP BY ROLLUP (method, bits)"))
def report_rollup(spark, sf_dir):
    return results(spark, sf_dir).rollup("method", "bits").agg(F.count("*").alias("n"), F.round(F.avg("hit"), 6).alias("recall")).fillna({"method": "all", "bits": 0})


@query(_report_sql("SELECT coalesce(method, 'all') AS method, coalesce(bits, 0) AS bits, coalesce(qid % 20, -1) AS part, count(*) AS n, round(avg(hit), 6) AS recall FROM r GROUP BY GROUPING SETS ((method, bits), (method, qid % 20), ())"))
def report_grouping_sets(spark, sf_dir):
    r = results(spark, sf_dir).withColumn("part", F.col("qid") % 20)
    return r.groupingSets([["method", "bits"], ["method", "part"], []], "method", "bits", "part").agg(F.count("*").alias("n"), F.round(F.avg("hit"), 6).alias("recall")).fillna({"method": "all", "bits": 0, "part": -1})


@query(_report_sql("SELECT bits, round(avg(hit) FILTER (WHERE method = 'pv'), 6) AS pv, round(avg(hit) FILTER (WHERE method = 'gl'), 6) AS gl FROM r GROUP BY bits"))
def recall_pivot(spark, sf_dir):
    return results(spark, sf_dir).groupBy("bits").pivot("method", ["pv", "gl"]).agg(F.round(F.avg("hit"), 6))


@query(f"WITH {KNN} SELECT e.label, count(*) AS n, count(*) FILTER (WHERE e.label = f.label) AS same, round(avg(CASE WHEN e.label = f.label THEN 1.0 ELSE 0.0 END), 6) AS rate FROM k JOIN emb e ON e.id = k.qid JOIN emb f ON f.id = k.id GROUP BY e.label")
def hit_rate_by_label(spark, sf_dir):
    lab = labels(spark, sf_dir)
    k = found(spark, sf_dir).join(lab.select(F.col("id").alias("qid"), "label"), "qid").join(lab.select("id", F.col("label").alias("other")), "id")
    return k.groupBy("label").agg(F.count("*").alias("n"), F.count_if(F.col("label") == F.col("other")).alias("same"), F.round(F.avg((F.col("label") == F.col("other")).cast("int")), 6).alias("rate"))


@query(f"WITH {KNN} SELECT round(quantile_cont(score, 0.1), 6) AS p10, round(quantile_cont(score, 0.5), 6) AS p50, round(quantile_cont(score, 0.9), 6) AS p90, round(var_pop(score), 9) AS var, round(avg(score), 6) AS mean FROM k")
def distance_percentiles(spark, sf_dir):
    k = found(spark, sf_dir)
    p = lambda x: F.round(F.percentile("score", F.lit(x)), 6)
    return k.agg(p(0.1).alias("p10"), p(0.5).alias("p50"), p(0.9).alias("p90"), F.round(F.var_pop("score"), 9).alias("var"), F.round(F.avg("score"), 6).alias("mean"))


@query(f"WITH {KNN}, s AS (SELECT qid, id, CAST(floor(score * 50) AS BIGINT) AS s FROM k) SELECT qid, id, row_number() OVER (PARTITION BY qid ORDER BY s DESC, id) AS rn, rank() OVER (PARTITION BY qid ORDER BY s DESC) AS rk, dense_rank() OVER (PARTITION BY qid ORDER BY s DESC) AS dr, ntile(4) OVER (PARTITION BY qid ORDER BY s DESC, id) AS nt, round(percent_rank() OVER (PARTITION BY qid ORDER BY s DESC), 6) AS pr FROM s")
def rank_variants(spark, sf_dir):
    s = found(spark, sf_dir).select("qid", "id", F.floor(F.col("score") * 50).cast("long").alias("s"))
    by, ties = Window.partitionBy("qid").orderBy(F.desc("s"), "id"), Window.partitionBy("qid").orderBy(F.desc("s"))
    long = lambda c, n: c.cast("long").alias(n)
    return s.select("qid", "id", long(F.row_number().over(by), "rn"), long(F.rank().over(ties), "rk"), long(F.dense_rank().over(ties), "dr"), long(F.ntile(4).over(by), "nt"), F.round(F.percent_rank().over(ties), 6).alias("pr"))


@query(f"WITH {KNN} SELECT qid, CAST(rank AS INTEGER) AS rank, coalesce(round(score - lag(score) OVER w, 6), 0) AS gap, coalesce(lead(id) OVER w, -1) AS next, first_value(id) OVER w AS nearest, nth_value(id, 3) OVER (PARTITION BY qid ORDER BY rank ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS third FROM k WINDOW w AS (PARTITION BY qid ORDER BY rank)")
def distance_gaps(spark, sf_dir):
    w = Window.partitionBy("qid").orderBy("rank")
    return found(spark, sf_dir).select("qid", "rank", F.coalesce(F.round(F.col("score") - F.lag("score").over(w), 6), F.lit(0.0)).alias("gap"), F.coalesce(F.lead("id").over(w), F.lit(-1)).alias("next"), F.first("id").over(w).alias("nearest"), F.nth_value("id", 3).over(w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)).alias("third"))


@query(f"WITH {APPROX} SELECT a.qid, CAST(a.rank AS INTEGER) AS rank, CAST(sum(CASE WHEN k.id IS NULL THEN 0 ELSE 1 END) OVER (PARTITION BY a.qid ORDER BY a.rank ROWS UNBOUNDED PRECEDING) AS BIGINT) AS common FROM a LEFT JOIN k ON k.qid = a.qid AND k.id = a.id")
def rolling_overlap(spark, sf_dir):
    hit = approx(spark, sf_dir).join(found(spark, sf_dir).select("qid", "id", F.lit(1).alias("hit")), ["qid", "id"], "left")
    w = Window.partitionBy("qid").orderBy("rank").rowsBetween(Window.unboundedPreceding, 0)
    return hit.select("qid", "rank", F.sum(F.coalesce("hit", F.lit(0))).over(w).cast("long").alias("common"))


@query("SELECT event_id, count(*) OVER w AS n, round(sum(CAST(value AS DECIMAL(18,4))) OVER w, 4)::DOUBLE AS total FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 DAY PRECEDING AND CURRENT ROW)")
def range_frame_events(spark, sf_dir):
    e = io.table(spark, sf_dir, "events").select("event_id", "user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("t"), F.col("value").cast("decimal(18,4)").alias("v"))
    w = Window.partitionBy("user_id").orderBy("t").rangeBetween(-86_400_000_000, 0)
    return e.select("event_id", F.count("*").over(w).alias("n"), F.sum("v").over(w).cast("double").alias("total"))


@query(f"WITH {B.DB} SELECT qid, id, round({B.score('q.vec', 'db.vec')}, 6) AS score FROM q, db ORDER BY {B.score('q.vec', 'db.vec')} DESC, qid, id LIMIT 25")
def topk_global(spark, sf_dir):
    """The best 25 of all pairs are among the best 25 of each query."""
    s = found(spark, sf_dir, 25).select("qid", "id", "score").orderBy(F.desc("score"), "qid", "id").limit(25)
    return s.withColumn("score", F.round("score", 6))


@query(f"WITH {B.DB} SELECT qid, CAST(rank AS INTEGER) AS rank, id FROM ({B.knn(k=5, kind='ip')})")
def topk_per_query(spark, sf_dir):
    return exact.exact_knn(io.base(spark, sf_dir), io.held_out(spark, sf_dir), 5, "ip").select("qid", "rank", "id")


@query("SELECT vec_id AS id FROM embeddings WHERE (vec_id * 7919 + 13) % 100 < 30")
def train_sample(spark, sf_dir):
    """The same sample in every engine: arithmetic on ids."""
    return io.vectors(spark, sf_dir).where((F.col("id") * 7919 + 13) % 100 < 30).select("id")


@query(f"WITH {APPROX} SELECT qid, id FROM a INTERSECT SELECT qid, id FROM k")
def hits_intersect(spark, sf_dir):
    return approx(spark, sf_dir).select("qid", "id").intersect(found(spark, sf_dir).select("qid", "id"))


@query(f"WITH {APPROX} SELECT qid, id FROM k EXCEPT ALL SELECT qid, id FROM a")
def misses_except(spark, sf_dir):
    return found(spark, sf_dir).select("qid", "id").exceptAll(approx(spark, sf_dir).select("qid", "id"))


@query(f"WITH {KNN} SELECT qid, CAST(rank AS INTEGER) AS rank, id FROM k")
def shard_union_topk(spark, sf_dir):
    """Best of each of four shards, merged."""
    db, out = io.base(spark, sf_dir), None
    for shard in range(4):
        one = found(spark, sf_dir, 10, db.where(F.col("id") % 4 == shard)).select("qid", "id", "score")
        out = one if out is None else out.unionByName(one)
    return exact.topk(out, 10).select("qid", "rank", "id")


@query(f"WITH {B.MEAN}, {B.pv(2)}, h AS (SELECT id, {B.text_of('list_transform(codes[1:6], lambda c: c)')} AS code FROM enc) SELECT code, count(*) AS n, min(id) AS first FROM h GROUP BY code HAVING count(*) > 1")
def duplicate_codes(spark, sf_dir):
    db = io.base(spark, sf_dir)
    c = model.centered(db, model.dataset_mean(db)).select("id", F.concat_ws(",", F.transform(F.slice(quantize.pvq("vec", 2)["codes"], 1, 6), lambda x: x.cast("string"))).alias("code"))
    return c.groupBy("code").agg(F.count("*").alias("n"), F.min("id").alias("first")).where("n > 1")


@query(f"WITH {B.DB} SELECT id, round(list_max(vec), 9) AS top FROM db WHERE list_max(vec) > (SELECT 0.8 * max(list_max(vec)) FROM db)")
def scalar_subquery_bound(spark, sf_dir):
    io.base(spark, sf_dir).createOrReplaceTempView("ve_db")
    return spark.sql("SELECT id, round(array_max(vec), 9) AS top FROM ve_db WHERE array_max(vec) > (SELECT 0.8D * max(array_max(vec)) FROM ve_db)")


@query(f"WITH {KNN} SELECT id FROM db WHERE EXISTS (SELECT 1 FROM k WHERE k.id = db.id AND k.rank = 1) AND id NOT IN (SELECT id FROM k WHERE rank = 2)")
def exists_neighbor(spark, sf_dir):
    found(spark, sf_dir).createOrReplaceTempView("ve_k")
    io.base(spark, sf_dir).createOrReplaceTempView("ve_db")
    return spark.sql("SELECT id FROM ve_db WHERE EXISTS (SELECT 1 FROM ve_k k WHERE k.id = ve_db.id AND k.rank = 1) AND id NOT IN (SELECT id FROM ve_k WHERE rank = 2)")


@query(
    "WITH f AS (SELECT c_custkey AS id, n_name, r_name, c_acctbal, count(o_orderkey) AS orders, coalesce(sum(CAST(o_totalprice AS DECIMAL(18,2))), 0)::DOUBLE AS spent FROM customer JOIN nation ON n_nationkey = c_nationkey "
    "JOIN region ON r_regionkey = n_regionkey LEFT JOIN orders ON o_custkey = c_custkey GROUP BY ALL) SELECT id, r_name, orders, round(c_acctbal / 10000, 6) AS x0, round(orders / 100.0::DOUBLE, 6) AS x1, round(spent / 1000000, 8) AS x2 FROM f"
)
def customer_profile_vectors(spark, sf_dir):
    """Vectors for recommendation: customers with what they bought, through the star's joins."""
    t = lambda n: io.table(spark, sf_dir, n)
    o = t("orders").groupBy(F.col("o_custkey").alias("c_custkey")).agg(F.count("*").alias("orders"), F.sum(F.col("o_totalprice").cast("decimal(18,2)")).cast("double").alias("spent"))
    n = t("nation").join(F.broadcast(t("region")), F.col("n_regionkey") == F.col("r_regionkey"))  # 25 and 5 rows
    c = t("customer").join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey")).join(o, "c_custkey", "left")
    orders, spent = F.coalesce("orders", F.lit(0)), F.coalesce("spent", F.lit(0.0))
    return c.select(F.col("c_custkey").alias("id"), "r_name", orders.alias("orders"), F.round(F.col("c_acctbal") / 10000, 6).alias("x0"), F.round(orders / 100, 6).alias("x1"), F.round(spent / 1000000, 8).alias("x2"))


@query(
    "WITH f AS (SELECT s_suppkey AS id, [s_acctbal / 10000, sum(CAST(l_quantity AS DECIMAL(18,2)))::DOUBLE / 10000, avg_d] AS vec FROM supplier JOIN "
    "(SELECT *, sum(CAST(l_discount AS DECIMAL(18,4))) OVER (PARTITION BY l_suppkey)::DOUBLE / count(*) OVER (PARTITION BY l_suppkey) * 10 AS avg_d FROM lineitem) ON l_suppkey = s_suppkey GROUP BY s_suppkey, s_acctbal, avg_d), "
    "q AS (SELECT id AS qid, vec FROM f WHERE id % 10 = 0), db AS (SELECT id, vec FROM f WHERE id % 10 <> 0) "
    f"SELECT qid, CAST(rank AS INTEGER) AS rank, id, round(score, 6) AS score FROM ({B.knn(k=3)})"
)
def supplier_profile_knn(spark, sf_dir):
    s = io.table(spark, sf_dir, "supplier").select("s_suppkey", "s_acctbal")
    items = io.table(spark, sf_dir, "lineitem").groupBy(F.col("l_suppkey").alias("s_suppkey")).agg(F.sum(F.col("l_quantity").cast("decimal(18,2)")).cast("double").alias("quantity"), (F.sum(F.col("l_discount").cast("decimal(18,4)")).cast("double") / F.count("*")).alias("discount"))
    f = s.join(items, "s_suppkey").select(F.col("s_suppkey").alias("id"), F.array(F.col("s_acctbal") / 10000, F.col("quantity") / 10000, F.col("discount") * 10).alias("vec"))
    return exact.exact_knn(f.where("id % 10 <> 0"), f.where("id % 10 = 0").withColumnRenamed("id", "qid"), 3).withColumn("score", F.round("score", 6))


RBO_P = 0.98


@query(
    f"WITH {B.MEAN}, {B.codec_sql('pv4')}, k AS ({B.knn(k=40)}), a AS ({B.knn('dec', k=40)}), b AS (SELECT a.qid, greatest(a.rank, k.rank) AS r FROM a JOIN k ON a.qid = k.qid AND a.id = k.id), "
    "d AS (SELECT s FROM range(1, 41) t(s)), o AS (SELECT q.qid, s, (SELECT count(*) FROM b WHERE b.qid = q.qid AND b.r <= s) AS x FROM q, d) "
    f"SELECT qid, round({1 - RBO_P} * sum(x / s::DOUBLE * pow({RBO_P}, s - 1)), 6) AS rbo, round({1 - RBO_P} * sum(x / s::DOUBLE * pow({RBO_P}, s - 1)) + max(CASE WHEN s = 40 THEN x END) / 40.0 * pow({RBO_P}, 40), 6) AS rbo_ext FROM o GROUP BY qid"
)
def rbo_candidates(spark, sf_dir):
    r = measures.rbo(approx(spark, sf_dir, "pv4", 40), found(spark, sf_dir, 40), 40, RBO_P)
    return r.select("qid", F.round("rbo", 6).alias("rbo"), F.round("rbo_ext", 6).alias("rbo_ext"))
