"""Measures on constants, distributions, and the batteries of scalar functions."""

from __future__ import annotations

import re
from collections import Counter



from pyspark.sql import functions as F

from vecengine.functions import pack, quantize
from vecengine.functions.vectors import sq_l2
from vecengine.operators import exact, measures, model
from vecengine.sources import embed, io
from vecengine.workloads import base as B
from vecengine.workloads.base import query

#: Order lines as vectors to store: dimension by quantity, code lengths and padding by line, supplier and part; n lines each.
_GRID = "SELECT CAST(l_quantity AS INTEGER) * 16 AS d, CAST(l_linenumber AS INTEGER) + 1 AS bits, CAST(l_suppkey % 3 AS INTEGER) * 4 AS bits2, CASE CAST(l_partkey % 3 AS INTEGER) WHEN 0 THEN 0 WHEN 1 THEN 1 ELSE 32 END AS pad, count(*) AS n FROM lineitem GROUP BY ALL"
_FOOT = "CAST(ceil((d * bits + 32) / (greatest(pad, 1) * 8.0)) * greatest(pad, 1) + ceil(d * bits2 / 8.0) AS BIGINT)"


def _grid(spark, sf_dir):
    part = F.pmod("l_partkey", F.lit(3))
    lines = io.table(spark, sf_dir, "lineitem").select(
        (F.col("l_quantity").cast("int") * 16).alias("d"), (F.col("l_linenumber").cast("int") + 1).alias("bits"), (F.pmod("l_suppkey", F.lit(3)).cast("int") * 4).alias("bits2"),
        F.when(part == 0, 0).when(part == 1, 1).otherwise(32).alias("pad"),
    )
    return lines.groupBy("d", "bits", "bits2", "pad").agg(F.count("*").alias("n"))


@query(
    f"WITH g AS ({_GRID}) SELECT d, bits, bits2, pad, n, {_FOOT} AS pv, CAST(ceil(d * bits / (greatest(pad, 1) * 8.0)) * greatest(pad, 1) + ceil(d * bits2 / 8.0) AS BIGINT) AS gl, "
    "CAST(d * 2 AS BIGINT) AS f16, CAST(d * 4 AS BIGINT) AS f32, round(32.0::DOUBLE / (d * bits), 6) AS constants_share FROM g"
)
def footprint_table(spark, sf_dir):
    d, b, b2, p = (F.col(c) for c in ("d", "bits", "bits2", "pad"))
    return _grid(spark, sf_dir).select(
        "d", "bits", "bits2", "pad", "n", pack.footprint(d, b, p, b2).alias("pv"), pack.footprint(d, b, p, b2, "gl").alias("gl"),
        pack.footprint(d, 16, 1, 0, "f16").alias("f16"), pack.footprint(d, 32, 1, 0, "f32").alias("f32"), F.round(32.0 / (d * b), 6).alias("constants_share"),
    )


@query(f"WITH g AS ({_GRID}) SELECT d, bits, bits2, pad, n, round(d * 4.0::DOUBLE / {_FOOT}, 4) AS cr FROM g")
def compression_ratio_table(spark, sf_dir):
    d = F.col("d")
    size = pack.footprint(d, F.col("bits"), F.col("pad"), F.col("bits2"))
    return _grid(spark, sf_dir).select("d", "bits", "bits2", "pad", "n", F.round(pack.compression_ratio(d, size), 4).alias("cr"))


@query(
    "WITH s AS (SELECT l_returnflag AS name, CAST(l_quantity AS INTEGER) * 16 AS d, count(*) AS n FROM lineitem GROUP BY ALL), r AS (SELECT * FROM (VALUES (32), (64), (128)) t(degree)), "
    "z AS (SELECT name, d, degree, n * (d * 4.0::DOUBLE + 4 * degree) AS full_bytes, n * (ceil((d * 4 + 32) / 8.0) + 4.0::DOUBLE * degree) AS pv4, n * (ceil((d * 8 + 32) / 256.0) * 32 + 4.0::DOUBLE * degree) AS pv8 FROM s, r) "
    "SELECT name, d, degree, round(full_bytes / 1048576, 1) AS mib_full, round(pv4 / 1048576, 1) AS mib_pv4, round(full_bytes / pv4, 2) AS ratio_pv4, round(full_bytes / pv8, 2) AS ratio_pv8 FROM z"
)
def memory_ratio_table(spark, sf_dir):
    """Memory to build: full precision against 4-bit codes, for the lines of each return flag and quantity as a set of vectors."""
    lines = io.table(spark, sf_dir, "lineitem").select(F.col("l_returnflag").alias("name"), (F.col("l_quantity").cast("int") * 16).alias("d"))
    s = lines.groupBy("name", "d").agg(F.count("*").alias("n")).withColumn("degree", F.explode(F.array(F.lit(32), F.lit(64), F.lit(128))))
    n, r, d = F.col("n").cast("double"), F.col("degree"), F.col("d")
    full, four, eight = (pack.index_bytes(n, v, r) for v in (d * 4, pack.footprint(d, 4), pack.footprint(d, 8, 32)))
    mib = lambda x: F.round(x / 2**20, 1)
    return s.select("name", "d", "degree", mib(full).alias("mib_full"), mib(four).alias("mib_pv4"), F.round(full / four, 2).alias("ratio_pv4"), F.round(full / eight, 2).alias("ratio_pv8"))


@query("SELECT l_linestatus AS mode, l_returnflag AS other, round(exp(avg(ln(l_extendedprice / l_quantity))), 4) AS geomean FROM lineitem WHERE l_extendedprice > 0 AND l_quantity > 0 GROUP BY ALL")
def geomean_ratio(spark, sf_dir):
    """The mean ratio of price to quantity, by status and flag of the line."""
    lines = io.table(spark, sf_dir, "lineitem").where("l_extendedprice > 0 AND l_quantity > 0")
    rows = lines.select(F.col("l_linestatus").alias("mode"), F.col("l_returnflag").alias("other"), (F.col("l_extendedprice") / F.col("l_quantity")).alias("ratio"))
    g = measures.geomean(rows, "ratio", "mode", "other")
    return g.withColumn("geomean", F.round("geomean", 4))


@query(
    "WITH r AS (SELECT l_suppkey AS method, l_orderkey AS run, l_linenumber AS w, 1 - l_discount AS recall, l_extendedprice AS qps FROM lineitem) "
    "SELECT a.method, a.run, a.w, round(a.recall, 6) AS recall, a.qps FROM r a WHERE NOT EXISTS (SELECT 1 FROM r b WHERE b.method = a.method AND b.recall >= a.recall AND b.qps >= a.qps AND (b.recall > a.recall OR b.qps > a.qps))"
)
def pareto_front(spark, sf_dir):
    """Lines that no other of their supplier beats in both discount left and price."""
    lines = io.table(spark, sf_dir, "lineitem").select(F.col("l_suppkey").alias("method"), F.col("l_orderkey").alias("run"), F.col("l_linenumber").alias("w"), (1 - F.col("l_discount")).alias("recall"), F.col("l_extendedprice").alias("qps"))
    return measures.pareto(lines).select("method", "run", "w", F.round("recall", 6).alias("recall"), "qps")


@query(
    f"WITH {B.MEAN}, g AS (SELECT max(list_max(vec)) - min(list_min(vec)) AS w FROM cen), c AS (SELECT id, unnest(range(0, len(vec))) AS j, unnest(vec) AS x FROM cen), p AS (SELECT avg(w) AS w FROM (SELECT max(x) - min(x) AS w FROM c GROUP BY j)) "
    "SELECT round(quantile_cont((list_max(vec) - list_min(vec)) / g.w, 0.95), 6) AS global_p95, round(quantile_cont((list_max(vec) - list_min(vec)) / p.w, 0.95), 6) AS dim_p95, round(avg((list_max(vec) - list_min(vec)) / g.w), 6) AS global_mean FROM cen, g, p"
)
def range_utilization(spark, sf_dir):
    db = io.base(spark, sf_dir)
    c = model.centered(db, model.dataset_mean(db))
    lo, hi = model.global_bounds(c)
    lows, highs = model.dim_bounds(c)
    width, dim = F.array_max("vec") - F.array_min("vec"), sum(h - x for x, h in zip(lows, highs, strict=True)) / len(lows)
    return c.agg(F.round(F.percentile(width / (hi - lo), F.lit(0.95)), 6).alias("global_p95"), F.round(F.percentile(width / dim, F.lit(0.95)), 6).alias("dim_p95"), F.round(F.avg(width / (hi - lo)), 6).alias("global_mean"))


_BIN = "CAST(greatest(0, least(19, floor((x + 0.5) / 0.05::DOUBLE))) AS INTEGER)"


@query(f"WITH {B.MEAN}, c AS (SELECT unnest(vec) AS x FROM cen) SELECT {_BIN} AS bin, count(*) AS n FROM c GROUP BY 1")
def dim_histogram(spark, sf_dir):
    db = io.base(spark, sf_dir)
    cells = model.centered(db, model.dataset_mean(db)).select(F.explode("vec").alias("x"))
    return measures.histogram(cells, "x", -0.5, 0.5, 20)


@query(
    f"WITH {B.MEAN}, c AS (SELECT 'before' AS stage, unnest(range(0, len(vec))) AS j, unnest(vec) AS x FROM db UNION ALL SELECT 'after', unnest(range(0, len(vec))), unnest(vec) FROM cen) "
    "SELECT stage, CAST(j AS INTEGER) AS j, round(avg(x), 6) AS mean, round(avg(x) - 2 * stddev_pop(x), 6) AS low, round(avg(x) + 2 * stddev_pop(x), 6) AS high FROM c GROUP BY stage, j"
)
def w14_distributions(spark, sf_dir):
    """Components before and after centering: mean and two deviations around it."""
    db = io.base(spark, sf_dir)
    both = db.select(F.lit("before").alias("stage"), F.posexplode("vec").alias("j", "x")).union(model.centered(db, model.dataset_mean(db)).select(F.lit("after"), F.posexplode("vec")))
    r = lambda c, n: F.round(c, 6).alias(n)
    a, s = F.avg("x"), F.stddev_pop("x")
    return both.groupBy("stage", "j").agg(r(a, "mean"), r(a - 2 * s, "low"), r(a + 2 * s, "high"))


def _mean_zero(x):
    """-0.0 and 0.0 alike."""
    return F.when(x == 0, F.lit(0.0)).otherwise(x)


def _codec_recalls(name: str, codecs, k: int = 10):
    ctes = ", ".join(B.codec_sql(c, f"d_{c}") for c in codecs)
    lists = ", ".join(f"a_{c} AS MATERIALIZED ({B.knn(f'd_{c}', k=k)})" for c in codecs)
    rows = " UNION ALL ".join(f"SELECT '{c}' AS codec, round(({B.recall_sql(f'a_{c}', 'k')}), 6) AS recall" for c in codecs)

    @query(f"WITH {B.MEAN}, k AS MATERIALIZED ({B.knn(k=k)}), {ctes}, {lists} {rows}", name)
    def run(spark, sf_dir):
        db, q = io.base(spark, sf_dir), io.held_out(spark, sf_dir)
        truth, mean, out = io.staged(exact.exact_knn(db, q, k), "truth"), model.dataset_mean(db), None
        for c in codecs:
            one = measures.recall(exact.exact_knn(model.encode(db, c, mean), q, k), truth, k).select(F.lit(c).alias("codec"), F.round("recall", 6).alias("recall"))
            out = one if out is None else out.unionByName(one)
        return out


_codec_recalls("w11_encodings", ("pv8", "pv4x4", "pv4x8", "gl8"))
_codec_recalls("w9_accuracy_ratio", ("pv2", "pv3", "pv4", "pv5", "pv6", "pv8", "gl2", "gl3", "gl4", "gl5", "gl6", "gl8"))
_codec_recalls("w8_candidates", ("pv4", "pv8", "pv16", "gl4", "gl8", "gl16"), 100)


@query(
    "WITH m AS (SELECT l_orderkey * 10 + l_linenumber AS id, [l_quantity, l_extendedprice, l_discount, l_tax] AS vec FROM lineitem), "
    "s AS (SELECT id, list_transform(range(1, 5), lambda i: vec[i] / [50.0::DOUBLE, 100000.0::DOUBLE, 0.1::DOUBLE, 0.08::DOUBLE][i]) AS vec FROM m), "
    + ", ".join(
        f"{t}_mu AS (SELECT j, round(CAST(sum(CAST(x AS DECIMAL(38,15))) AS DOUBLE) / count(*), 12) AS mu FROM (SELECT unnest(range(0, 4)) AS j, unnest(vec) AS x FROM {t}) GROUP BY j), {t}_m AS (SELECT list(mu ORDER BY j) AS m FROM {t}_mu), "
        f"{t}_c AS (SELECT id, list_transform(range(1, 5), lambda i: vec[i] - m[i]) AS vec FROM {t}, {t}_m), {B.pv(8, f'{t}_c', f'{t}_e')}, "
        f"{t}_u AS (SELECT unnest(list_transform(range(1, 5), lambda i: abs(vec[i] - (lo + step * CAST(codes[i] AS DOUBLE))))) AS err, unnest(range(0, 4)) AS j FROM {t}_e)"
        for t in ("m", "s")
    )
    + " SELECT 'raw' AS kind, CAST(j AS INTEGER) AS j, round(avg(err), 6) AS err FROM m_u GROUP BY j UNION ALL SELECT 'scaled', CAST(j AS INTEGER), round(avg(err), 6) FROM s_u GROUP BY j"
)
def w15_variance(spark, sf_dir):
    """Columns of very different spread: the error of the small ones drowns unless they are scaled first."""
    rows = io.table(spark, sf_dir, "lineitem")
    raw = rows.select((F.col("l_orderkey") * 10 + F.col("l_linenumber")).alias("id"), F.array("l_quantity", "l_extendedprice", "l_discount", "l_tax").alias("vec"))
    scaled = raw.withColumn("vec", F.zip_with("vec", F.array(*(F.lit(x) for x in (50.0, 100000.0, 0.1, 0.08))), lambda x, s: x / s))
    out = None
    for kind, db in (("raw", raw), ("scaled", scaled)):
        q = model.centered(db, model.dataset_mean(db)).withColumn("q", quantize.pvq("vec", 8))
        err = q.select(F.posexplode(F.zip_with("vec", quantize.decode("q"), lambda x, y: F.abs(x - y))).alias("j", "err"))
        one = err.groupBy("j").agg(F.round(F.avg("err"), 6).alias("err")).select(F.lit(kind).alias("kind"), "j", "err")
        out = one if out is None else out.unionByName(one)
    return out


@query(
    "SELECT l_orderkey, l_linenumber, floor(l_quantity / 7)::BIGINT AS fl, floor(l_quantity / 2 + 0.5)::BIGINT AS half_up, round_even(l_quantity / 2, 0) AS half_even, round(sqrt(l_extendedprice), 6) AS root, round(exp(l_tax), 6) AS ex, round(ln(l_extendedprice), 6) AS lg, "
    "round(log2(l_extendedprice), 6) AS l2, round(pow(l_discount, 2), 6) AS sq, abs(l_quantity - 25) AS ab, sign(l_quantity - 25)::INTEGER AS sg, greatest(l_tax, l_discount) AS hi, least(l_tax, l_discount) AS lo, coalesce(CASE WHEN l_discount <> 0 THEN round(l_tax / l_discount, 6) END, -1) AS ratio, round(pi() * l_quantity, 6) AS turn FROM lineitem"
)
def math_battery(spark, sf_dir):
    c, r = F.col, lambda x: F.round(x, 6)
    return io.table(spark, sf_dir, "lineitem").select(
        "l_orderkey", "l_linenumber", F.floor(c("l_quantity") / 7).alias("fl"), F.floor(c("l_quantity") / 2 + 0.5).alias("half_up"), F.bround(c("l_quantity") / 2).alias("half_even"), r(F.sqrt("l_extendedprice")).alias("root"),
        r(F.exp("l_tax")).alias("ex"), r(F.ln("l_extendedprice")).alias("lg"), r(F.log2("l_extendedprice")).alias("l2"), r(F.pow("l_discount", 2)).alias("sq"), F.abs(c("l_quantity") - 25).alias("ab"), F.signum(c("l_quantity") - 25).cast("int").alias("sg"),
        F.greatest("l_tax", "l_discount").alias("hi"), F.least("l_tax", "l_discount").alias("lo"), F.coalesce(r(F.try_divide("l_tax", "l_discount")), F.lit(-1.0)).alias("ratio"), r(F.pi() * c("l_quantity")).alias("turn"),
    )


@query(
    f"WITH {B.DB} SELECT id, round(list_min(vec), 9) AS lo, round(list_max(vec), 9) AS hi, len(list_filter(vec, lambda x: x > 0)) AS positive, len(list_filter(vec, lambda x: x > 0.3)) > 0 AS big, len(list_filter(vec, lambda x: abs(x) < 1)) = len(vec) AS inside, round(vec[1:3][2], 9) AS second, "
    "CAST(list_position(vec, list_max(vec)) AS BIGINT) AS top, round(list_sort(vec)[32], 9) AS median, CAST(len(list_intersect(list_distinct(list_transform(vec, lambda x: floor(x * 10))), [0.0::DOUBLE, 1.0::DOUBLE, 2.0::DOUBLE])) AS BIGINT) AS common, CAST(len(list_distinct(list_transform(vec, lambda x: floor(x * 10)))) AS BIGINT) AS levels FROM db"
)
def array_battery(spark, sf_dir):
    tens = F.transform("vec", lambda x: F.floor(x * 10).cast("double"))
    return io.base(spark, sf_dir).select(
        "id", F.round(F.array_min("vec"), 9).alias("lo"), F.round(F.array_max("vec"), 9).alias("hi"), F.size(F.filter("vec", lambda x: x > 0)).cast("long").alias("positive"), F.exists("vec", lambda x: x > 0.3).alias("big"),
        F.forall("vec", lambda x: F.abs(x) < 1).alias("inside"), F.round(F.element_at(F.slice("vec", 1, 3), 2), 9).alias("second"), F.array_position("vec", F.array_max("vec")).alias("top"), F.round(F.element_at(F.array_sort("vec"), 32), 9).alias("median"),
        F.size(F.array_intersect(tens, F.array(F.lit(0.0), F.lit(1.0), F.lit(2.0)))).cast("long").alias("common"), F.size(F.array_distinct(tens)).cast("long").alias("levels"),
    )


_TOKENS = "SELECT doc_id, unnest(regexp_split_to_array(lower(text), '[^a-z]+')) AS w FROM documents"


@query(f"WITH t AS ({_TOKENS}) SELECT doc_id, count(*) AS words, count(DISTINCT w) AS kinds, max(length(w)) AS longest, substr(md5(string_agg(w, ' ' ORDER BY w)), 1, 8) AS digest FROM t WHERE w <> '' GROUP BY doc_id")
def tokenize_docs(spark, sf_dir):
    t = io.table(spark, sf_dir, "documents").select("doc_id", F.explode(F.split(F.lower("text"), "[^a-z]+")).alias("w")).where("w <> ''")
    words = t.groupBy("doc_id").agg(F.count("*").alias("words"), F.countDistinct("w").alias("kinds"), F.max(F.length("w")).cast("long").alias("longest"), F.sort_array(F.collect_list("w")).alias("all"))
    return words.select("doc_id", "words", "kinds", "longest", F.substring(F.md5(F.concat_ws(" ", "all")), 1, 8).alias("digest"))


@query(
    f"WITH t AS (SELECT doc_id, w, count(*) AS n FROM ({_TOKENS}) WHERE w <> '' GROUP BY doc_id, w), b AS (SELECT unnest(regexp_split_to_array(lower(text), '[^a-z]+')) AS w FROM (SELECT text FROM benchmark ORDER BY item_id LIMIT 1)), "
    "m AS (SELECT w, count(*) AS n FROM b WHERE w <> '' GROUP BY w) SELECT doc_id, CAST(sum(t.n * m.n) AS BIGINT) AS dot FROM t JOIN m ON m.w = t.w GROUP BY doc_id"
)
def sparse_dot_map(spark, sf_dir):
    """Inner products of the documents' sparse token vectors, kept as maps, with that of one question."""
    t = io.table(spark, sf_dir, "documents").select("doc_id", F.explode(F.split(F.lower("text"), "[^a-z]+")).alias("w")).where("w <> ''")
    n = t.groupBy("doc_id", "w").agg(F.count("*").alias("n")).groupBy("doc_id").agg(F.map_from_entries(F.collect_list(F.struct("w", "n"))).alias("m"))
    asked = io.table(spark, sf_dir, "benchmark").orderBy("item_id").select("text").first()["text"]
    words = Counter(re.findall("[a-z]+", asked.lower()))
    one = F.create_map(*(x for w, c in sorted(words.items()) for x in (F.lit(w), F.lit(c).cast("long"))))
    both = F.map_filter(F.map_zip_with("m", one, lambda _, p, q: p * q), lambda _, v: v.isNotNull())
    return n.select("doc_id", F.aggregate(F.map_values(both), F.lit(0).cast("long"), lambda s, v: s + v).alias("dot")).where("dot > 0")


@query("SELECT user_id, CAST(date_trunc('day', ts) AS DATE)::VARCHAR AS day, count(*) FILTER (WHERE event_type = 'view') AS views, count(*) FILTER (WHERE event_type = 'purchase') AS purchases, CAST(sum(CAST(value AS DECIMAL(18,4))) AS DOUBLE) AS total, CAST(max(date_diff('day', DATE '2024-01-01', CAST(ts AS DATE))) AS INTEGER) AS age FROM events GROUP BY user_id, CAST(date_trunc('day', ts) AS DATE)")
def daily_vectors(spark, sf_dir):
    e = io.table(spark, sf_dir, "events").withColumn("day", F.date_trunc("day", F.col("ts").cast("timestamp")).cast("date"))
    return e.groupBy("user_id", "day").agg(
        F.count_if(F.col("event_type") == "view").alias("views"), F.count_if(F.col("event_type") == "purchase").alias("purchases"), F.sum(F.col("value").cast("decimal(18,4)")).cast("double").alias("total"), F.max(F.datediff("day", F.lit("2024-01-01").cast("date"))).alias("age")
    ).withColumn("day", F.col("day").cast("string"))


@query("SELECT event_id, CAST(json_extract_string(props, '$.k') AS INTEGER) AS k, CAST(json_extract_string(props, '$.k') AS INTEGER) % 2 = 0 AS even FROM events")
def props_k_extract(spark, sf_dir):
    """One key three ways: by path, by schema, and as a variant."""
    e = io.table(spark, sf_dir, "events").select("event_id", F.get_json_object("props", "$.k").cast("int").alias("k"), F.from_json("props", "k int")["k"].alias("k2"), F.try_variant_get(F.parse_json("props"), "$.k", "int").alias("k3"))
    return e.where("k = k2 AND k = k3").select("event_id", "k", (F.col("k") % 2 == 0).alias("even"))


_BITS = f"WITH {B.DB}, s AS (SELECT id, list_reduce(list_transform(range(1, 33), lambda i: CASE WHEN vec[i] > 0 THEN CAST(1 AS BIGINT) << (i - 1) ELSE 0 END), lambda s, x: s + x) AS sig FROM db), t AS (SELECT qid, list_reduce(list_transform(range(1, 33), lambda i: CASE WHEN vec[i] > 0 THEN CAST(1 AS BIGINT) << (i - 1) ELSE 0 END), lambda s, x: s + x) AS sig FROM q)"


@query(f"{_BITS} SELECT qid, id, bit_count(xor(s.sig, t.sig))::INTEGER AS far FROM s, t QUALIFY row_number() OVER (PARTITION BY qid ORDER BY bit_count(xor(s.sig, t.sig)), id) <= 5")
def hamming_knn(spark, sf_dir):
    """Nearest by the signs of 32 components."""
    sig = F.aggregate(F.transform(F.slice("vec", 1, 32), lambda x, i: F.when(x > 0, F.expr("1L")).otherwise(F.expr("0L")) * F.pow(F.lit(2.0), i).cast("long")), F.lit(0).cast("long"), lambda s, x: s + x)
    s, t = io.base(spark, sf_dir).select("id", sig.alias("sig")), io.held_out(spark, sf_dir).select("qid", sig.alias("tig"))
    far = s.crossJoin(F.broadcast(t)).select("qid", "id", (-F.bit_count(F.col("sig").bitwiseXOR(F.col("tig")))).alias("score"))
    return exact.topk(far, 5).select("qid", "id", (-F.col("score")).cast("int").alias("far"))


@query(
    f"WITH {B.EMB}, v AS (SELECT id, CASE WHEN id % 7 = 0 THEN NULL ELSE vec END AS a, list_transform(vec, lambda x: -x) AS b FROM emb) SELECT id, coalesce(round(sqrt({B.sq_l2('a', 'b')}), 6), -1) AS d, coalesce(TRY_CAST(CASE WHEN id % 5 = 0 THEN 'x' ELSE id::VARCHAR END AS BIGINT), -1) AS n, coalesce(nullif(id % 3, 0), 9) AS z FROM v"
)
def null_safe_dist(spark, sf_dir):
    v = io.vectors(spark, sf_dir).select("id", F.when(F.col("id") % 7 != 0, F.col("vec")).alias("a"), F.transform("vec", lambda x: -x).alias("b"))
    tried = F.expr("try_cast(CASE WHEN id % 5 = 0 THEN 'x' ELSE cast(id AS string) END AS bigint)")
    return v.select("id", F.coalesce(F.round(F.sqrt(sq_l2("a", "b")), 6), F.lit(-1.0)).alias("d"), F.coalesce(tried, F.lit(-1)).alias("n"), F.coalesce(F.nullif(F.col("id") % 3, F.lit(0)), F.lit(9)).alias("z"))


@query("SELECT page_id, length(trim(regexp_replace(regexp_replace(regexp_replace(html, '<(script|style)[^>]*>[^<]*</(script|style)>', ' ', 'g'), '<[^>]*>', ' ', 'g'), '[ \\t\\r\\n]+', ' ', 'g'), ' ')) AS n FROM pages")
def page_text_len(spark, sf_dir):
    return io.table(spark, sf_dir, "pages").select("page_id", F.length(embed.page_text("html")).cast("long").alias("n"))


_EMBED = (
    "t AS (SELECT doc_id, unnest(regexp_split_to_array(lower(text), '[^a-z]+')) AS w FROM documents), h AS (SELECT doc_id, ('0x' || substr(md5(w), 1, 7))::BIGINT AS h, ('0x' || substr(md5(w), 8, 1))::BIGINT AS s FROM t WHERE w <> ''), "
    "c AS (SELECT doc_id, h % 96 AS j, sum(CASE WHEN s < 8 THEN 1 ELSE -1 END) AS x FROM h GROUP BY ALL), n AS (SELECT doc_id, CAST(sum(x * x) AS DOUBLE) AS n FROM c GROUP BY doc_id)"
)


@query(f"WITH {_EMBED} SELECT c.doc_id AS id, CAST(j AS INTEGER) AS j, round(x / sqrt(n), 9) AS x FROM c JOIN n ON n.doc_id = c.doc_id WHERE x <> 0")
def hash_embed_docs(spark, sf_dir):
    """Texts as unit vectors of signed token counts, 96 dimensions."""
    e = embed.hash_embed(io.table(spark, sf_dir, "documents"), 96, "doc_id", "text")
    return e.select("id", F.posexplode("vec").alias("j", "x")).where("x <> 0").withColumn("x", F.round("x", 9))


@query("SELECT o_orderkey, o_totalprice, o_orderpriority FROM orders")
def roundtrip_orc(spark, sf_dir):
    """Written as ORC, JSON and CSV and read back; all three must agree."""
    o = io.table(spark, sf_dir, "orders").select("o_orderkey", "o_totalprice", "o_orderpriority")
    import uuid

    out = None
    for fmt in ("orc", "json", "csv"):
        path = f"{io.shared_dir(spark)}/trip-{uuid.uuid4().hex}"
        io.write_any(o, path, fmt)
        back = io.read_any(spark, path, fmt, o.schema)
        out = back if out is None else out.intersectAll(back)
    return out


