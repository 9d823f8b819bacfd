"""Streaming methods in batch form, their streams, and the SQL surface."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from vecengine.functions import sqlfuncs
from vecengine.functions.vectors import sim
from vecengine.operators import exact, measures, model
from vecengine.sources import io
from vecengine.streaming import flows
from vecengine.workloads import base as B
from vecengine.workloads.base import query


@query("SELECT strftime(time_bucket(INTERVAL 1 HOUR, ts), '%Y-%m-%d %H:%M:%S') AS start, event_type, count(*) AS n, CAST(sum(CAST(value AS DECIMAL(18,4))) AS DOUBLE) AS total FROM events GROUP BY ALL")
def tumbling_event_counts(spark, sf_dir):
    w = flows.windowed_counts(io.table(spark, sf_dir, "events"), "1 hour")
    return w.withColumn("start", F.date_format("start", "yyyy-MM-dd HH:mm:ss"))


@query(
    "WITH w AS (SELECT time_bucket(INTERVAL 1 HOUR, ts) - k * INTERVAL 1 HOUR AS start, event_type, value FROM events, range(0, 3) r(k)) "
    "SELECT strftime(start, '%Y-%m-%d %H:%M:%S') AS start, event_type, count(*) AS n, CAST(sum(CAST(value AS DECIMAL(18,4))) AS DOUBLE) AS total FROM w GROUP BY ALL"
)
def sliding_event_mean(spark, sf_dir):
    w = flows.windowed_counts(io.table(spark, sf_dir, "events"), "3 hours", "1 hour")
    return w.withColumn("start", F.date_format("start", "yyyy-MM-dd HH:mm:ss"))


@query(
    "WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events), "
    "s AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g) "
    "SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM s GROUP BY user_id, k"
)
def session_users(spark, sf_dir):
    return flows.sessions(io.table(spark, sf_dir, "events")).withColumn("start", F.date_format("start", "yyyy-MM-dd HH:mm:ss"))


@query("WITH l AS (SELECT user_id, arg_max(event_id, (ts, event_id)) AS event_id, arg_max(event_type, (ts, event_id)) AS event_type FROM events GROUP BY user_id) SELECT user_id, event_id, event_type FROM l WHERE event_type <> 'error'")
def latest_state(spark, sf_dir):
    log = io.table(spark, sf_dir, "events").select("user_id", "event_id", "event_type", "ts")
    return flows.latest_state(log, "user_id", ["ts", "event_id"], "event_type", "error").select("user_id", "event_id", "event_type")


@query("SELECT c.event_id AS click, p.event_id AS purchase FROM events c JOIN events p ON c.user_id = p.user_id AND p.ts >= c.ts AND p.ts <= c.ts + INTERVAL 1 HOUR WHERE c.event_type = 'click' AND p.event_type = 'purchase'")
def click_purchase_join(spark, sf_dir):
    e = io.table(spark, sf_dir, "events").select("event_id", "user_id", "event_type", F.col("ts").cast("timestamp").alias("ts"))
    c = e.where("event_type = 'click'").select(F.col("event_id").alias("click"), F.col("user_id").alias("u"), F.col("ts").alias("t"))
    p = e.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), "user_id", "ts")
    return c.join(p, (F.col("u") == F.col("user_id")) & (F.col("ts") >= F.col("t")) & (F.col("ts") <= F.col("t") + F.expr("INTERVAL 1 HOUR"))).select("click", "purchase")


@query(
    f"WITH {B.EMB}, db AS (SELECT id, vec FROM emb WHERE id % 10 <> 0 AND label < 5), q AS (SELECT id AS qid, vec FROM emb WHERE id % 10 = 0), n AS (SELECT id, vec FROM emb WHERE id % 10 <> 0), "
    "c0 AS (SELECT unnest(range(0, len(vec))) AS j, unnest(vec) AS x FROM db), c1 AS (SELECT unnest(range(0, len(vec))) AS j, unnest(vec) AS x FROM n), "
    "m0 AS (SELECT j, round(CAST(sum(CAST(x AS DECIMAL(38,15))) AS DOUBLE) / count(*), 12) AS mu FROM c0 GROUP BY j), m1 AS (SELECT j, round(CAST(sum(CAST(x AS DECIMAL(38,15))) AS DOUBLE) / count(*), 12) AS mu FROM c1 GROUP BY j) "
    "SELECT round(sqrt(sum((m0.mu - m1.mu) * (m0.mu - m1.mu))), 6) AS drift, sqrt(sum((m0.mu - m1.mu) * (m0.mu - m1.mu))) > 0.05 AS refit FROM m0 JOIN m1 ON m0.j = m1.j"
)
def refit_after_drift(spark, sf_dir):
    """The mean was fitted to half of the labels; the rest arrives."""
    v = io.vectors(spark, sf_dir).where("id % 10 <> 0")
    far, again = flows.drift(model.dataset_mean(v.where("label < 5")), model.dataset_mean(v), 0.05)
    return spark.createDataFrame([(round(far, 6), again)], "drift double, refit boolean")


@query()
def w16_drift(spark, sf_dir):
    """Recall with codes of an outdated mean, and after fitting anew."""
    v = io.vectors(spark, sf_dir).withColumn("vec", F.transform("vec", lambda x, i: x + F.col("label") / 20 * (i % 8 - 3.5)))
    db, q = v.where("id % 10 <> 0"), v.where("id % 10 = 0").withColumnRenamed("id", "qid")
    truth, out = io.staged(exact.exact_knn(db, q, 10), "truth"), None
    for name, mean in (("outdated", model.dataset_mean(db.where("label < 2"))), ("fitted", model.dataset_mean(db))):
        one = measures.recall(exact.exact_knn(model.encode(db, "pv4", mean), q, 10), truth, 10).select(F.lit(name).alias("mean"), F.round("recall", 6).alias("recall"))
        out = one if out is None else out.unionByName(one)
    return out


def _stream(spark, df, n: int = 4):
    path = f"{io.shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    df.repartition(n).write.parquet(path)
    return spark.readStream.schema(df.schema).option("maxFilesPerTrigger", 1).parquet(path)


@query(f"WITH {B.DB} SELECT CAST(j AS INTEGER) AS j, count(*) AS n, round(sum(x) / count(*), 9) AS mu FROM (SELECT unnest(range(0, len(vec))) AS j, unnest(vec) AS x FROM db) GROUP BY j")
def stream_mean(spark, sf_dir):
    """The mean of a stream of files equals that of the table."""
    s = flows.running_mean(_stream(spark, io.base(spark, sf_dir)))
    done = flows.drain(spark, s, f"mean_{uuid.uuid4().hex}")
    return done.select("j", "n", F.round(F.col("s") / F.col("n"), 9).alias("mu"))


@query(f"WITH {B.MEAN}, {B.pv(8)} SELECT id, {B.text_of('codes')} AS codes, 3 AS model_version FROM enc")
def stream_encode(spark, sf_dir):
    db = io.base(spark, sf_dir)
    s = flows.encode_stream(_stream(spark, db), model.dataset_mean(db), 8, 3)
    done = flows.drain(spark, s, f"codes_{uuid.uuid4().hex}", "append")
    return done.select("id", F.concat_ws(",", F.transform("q.codes", lambda c: c.cast("string"))).alias("codes"), "model_version")


@query(f"WITH {B.DB} SELECT qid, CAST(rank AS INTEGER) AS rank, id FROM ({B.knn(k=5)})")
def standing_knn(spark, sf_dir):
    path = f"{io.shared_dir(spark)}/standing-{uuid.uuid4().hex}"
    asks = _stream(spark, io.held_out(spark, sf_dir), 2)
    run = flows.standing_knn(asks, io.base(spark, sf_dir), lambda df, _: df.select("qid", "rank", "id").write.mode("append").parquet(path)).trigger(availableNow=True).start()
    run.awaitTermination()
    return spark.read.parquet(path)


@query(f"WITH {B.DB} SELECT qid, id, round({B.score('q.vec', 'db.vec')} * -1, 9) AS l2, round({B.dot('q.vec', 'db.vec')}, 9) AS ip FROM db, (SELECT qid, vec FROM q ORDER BY qid LIMIT 1) q")
def sql_vec_l2(spark, sf_dir):
    sqlfuncs.register(spark)
    io.base(spark, sf_dir).createOrReplaceTempView("ve_db")
    io.held_out(spark, sf_dir).orderBy("qid").limit(1).createOrReplaceTempView("ve_q")
    return spark.sql("SELECT qid, id, round(vec_l2(q.vec, d.vec), 9) AS l2, round(vec_ip(q.vec, d.vec), 9) AS ip FROM ve_q q CROSS JOIN ve_db d")


@query(f"WITH {B.MEAN}, {B.pv(8)} SELECT id, upper(array_to_string(list_transform(codes, lambda c: printf('%02x', c)), '')) AS code, round(step, 9) AS step FROM enc")
def udf_arrow_encode(spark, sf_dir):
    db = io.base(spark, sf_dir)
    c = model.centered(db, model.dataset_mean(db)).select("id", sqlfuncs.pvq_pack("vec", F.lit(8)).alias("p"))
    return c.select("id", F.hex("p.code").alias("code"), F.round("p.step", 9).alias("step"))


@query(f"WITH {B.EMB} SELECT label, CAST(j AS INTEGER) AS j, round(avg(x), 9) AS mu FROM (SELECT label, unnest(range(0, len(vec))) AS j, unnest(vec) AS x FROM emb) GROUP BY label, j")
def udaf_mean(spark, sf_dir):
    m = io.vectors(spark, sf_dir).groupBy("label").agg(sqlfuncs.vec_mean("vec").alias("m"))
    return m.select("label", F.posexplode("m").alias("j", "mu")).withColumn("mu", F.round("mu", 9))


_TUMBLING = "SELECT strftime(time_bucket(INTERVAL 1 HOUR, ts), '%Y-%m-%d %H:%M:%S') AS start, event_type, count(*) AS n, CAST(sum(CAST(value AS DECIMAL(18,4))) AS DOUBLE) AS total FROM events GROUP BY ALL"


@query(_TUMBLING)
def stream_tumbling(spark, sf_dir):
    """The same windows from a stream of files, with a watermark longer than the events are spread."""
    w = flows.windowed_counts(_stream(spark, io.table(spark, sf_dir, "events")), "1 hour", late="3650 days")
    done = flows.drain(spark, w, f"windows_{uuid.uuid4().hex}")
    return done.withColumn("start", F.date_format("start", "yyyy-MM-dd HH:mm:ss"))


@query("SELECT event_type, count(*) AS n, count(DISTINCT event_id) AS kinds FROM events GROUP BY event_type")
def stream_dedup(spark, sf_dir):
    """Every event arrives twice; each is kept once."""
    e = io.table(spark, sf_dir, "events").select("event_id", "event_type", "ts")
    s = flows.deduplicated(_stream(spark, e.union(e)), ["event_id"], "3650 days")
    done = flows.drain(spark, s, f"once_{uuid.uuid4().hex}", "append")
    return done.groupBy("event_type").agg(F.count("*").alias("n"), F.countDistinct("event_id").alias("kinds"))


@query("SELECT c.event_id AS first, p.event_id AS \"then\" FROM events c JOIN events p ON c.user_id = p.user_id AND p.ts >= c.ts AND p.ts <= c.ts + INTERVAL 1 HOUR WHERE c.event_type = 'click' AND p.event_type = 'purchase'")
def stream_click_purchase(spark, sf_dir):
    """Two streams joined within an hour."""
    e = io.table(spark, sf_dir, "events").select("event_id", "user_id", "event_type", "ts")
    clicks, buys = (_stream(spark, e.where(F.col("event_type") == kind).drop("event_type"), 2) for kind in ("click", "purchase"))
    return flows.drain(spark, flows.followed(clicks, buys, "user_id", "1 HOUR", "3650 days"), f"followed_{uuid.uuid4().hex}", "append")


_KINDS = ("view", "click", "purchase", "signup", "error")


@query("SELECT user_id, count(*) AS n, round(sum(value), 4) AS total, " + " || ',' || ".join(f"CAST(count(*) FILTER (WHERE event_type = '{k}') AS VARCHAR)" for k in _KINDS) + " AS counts FROM events GROUP BY user_id")
def stateful_user_vectors(spark, sf_dir):
    """Vectors of users, kept as state while their events arrive."""
    s = flows.user_vectors(_stream(spark, io.table(spark, sf_dir, "events")), list(_KINDS))
    done = flows.drain(spark, s, f"users_{uuid.uuid4().hex}", "update")
    last = done.groupBy("user_id").agg(F.max_by(F.struct("n", "total", "counts"), "n").alias("r")).select("user_id", "r.*")
    return last.select("user_id", "n", F.round("total", 4).alias("total"), F.concat_ws(",", F.transform("counts", lambda c: c.cast("string"))).alias("counts"))


_LOG = "l AS (SELECT user_id AS id, arg_max(event_type, (ts, event_id)) AS op FROM events GROUP BY user_id)"


@query(f"WITH {B.EMB}, {_LOG}, db AS (SELECT emb.id, CASE WHEN op = 'purchase' THEN list_transform(vec, lambda x: -x) ELSE vec END AS vec FROM emb LEFT JOIN l ON l.id = emb.id WHERE emb.id % 10 <> 0 AND coalesce(op, '') <> 'error'), q AS (SELECT id AS qid, vec FROM emb WHERE id % 10 = 0) SELECT qid, CAST(rank AS INTEGER) AS rank, id FROM ({B.knn()})")
def delta_search(spark, sf_dir):
    """Search after a log: a user's last event deletes the vector (error), turns it (purchase) or keeps it."""
    base = io.base(spark, sf_dir)
    log = io.table(spark, sf_dir, "events").select(F.col("user_id").alias("id"), "event_id", "event_type", "ts")
    changed = log.join(base, "id").withColumn("vec", F.when(F.col("event_type") == "purchase", F.transform("vec", lambda x: -x)).otherwise(F.col("vec")))
    now = flows.merged(base, changed, "id", ["ts", "event_id"], "event_type", "error")
    return exact.exact_knn(now, io.held_out(spark, sf_dir), 10).select("qid", "rank", "id")


@query(f"WITH {B.MEAN}, {B.pv(4)} SELECT id, CAST(unnest(range(0, len(codes))) AS INTEGER) AS j, unnest(codes) AS code, round(unnest(list_transform(codes, lambda c: lo + step * c)), 9) AS approx FROM enc")
def udtf_cells(spark, sf_dir):
    """Codes as rows by a table function, joined laterally."""
    sqlfuncs.register(spark)
    db = io.base(spark, sf_dir)
    model.centered(db, model.dataset_mean(db)).createOrReplaceTempView("ve_centered")
    return spark.sql("SELECT id, j, code, round(approx, 9) AS approx FROM ve_centered, LATERAL pvq_cells(vec, 4)")


@query(f"WITH {B.DB}, s AS (SELECT id, {B.score('a.vec', 'db.vec')} AS score FROM db, (SELECT vec FROM q ORDER BY qid LIMIT 1) a) SELECT id, round(score, 6) AS score FROM s ORDER BY score DESC, id LIMIT 10")
def udtf_best(spark, sf_dir):
    """The ten best rows for one query by a table function over partitions, merged."""
    sqlfuncs.register(spark)
    one = F.array(*(F.lit(float(x)) for x in io.held_out(spark, sf_dir).orderBy("qid").first()["vec"]))
    scored = io.base(spark, sf_dir).select("id", sim(one, "vec").alias("score"), F.pmod("id", F.lit(8)).alias("part"))
    scored.createOrReplaceTempView("ve_scored")
    parts = spark.sql("SELECT * FROM best_of(row => TABLE(SELECT * FROM ve_scored) PARTITION BY part, k => 10)")
    return parts.orderBy(F.desc("score"), "id").limit(10).select("id", F.round("score", 6).alias("score"))


@query(f"WITH {B.MEAN}, {B.pv(4)} SELECT id, {B.text_of('codes')} AS codes FROM enc")
def sql_pvq_codes(spark, sf_dir):
    sqlfuncs.register(spark)
    db = io.base(spark, sf_dir)
    model.centered(db, model.dataset_mean(db)).createOrReplaceTempView("ve_centered")
    return spark.sql("SELECT id, array_join(transform(pvq_codes(vec, 15), c -> cast(c AS string)), ',') AS codes FROM ve_centered")
