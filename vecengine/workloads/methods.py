"""Quantizers, similarities, exact search, and the recall of every codec."""

from __future__ import annotations

from pyspark.sql import functions as F

from vecengine.functions import pack, quantize
from vecengine.functions.vectors import center, dot, norm, normalize, sim, sq_l2, total
from vecengine.operators import exact, measures, model
from vecengine.sources import io
from vecengine.workloads import base as B
from vecengine.workloads.base import query


def _joined(codes):
    return F.concat_ws(",", F.transform(codes, lambda c: c.cast("string")))


def _cells(df, vec, *keys):
    return df.select(*keys, F.posexplode(vec).alias("j", "x")).withColumn("x", F.round("x", 6))


def _cells_sql(source: str, key: str = "id") -> str:
    return f"SELECT {key}, CAST(unnest(range(0, len(vec))) AS INTEGER) AS j, round(unnest(vec), 6) AS x FROM {source}"


@query(
    "WITH b AS (SELECT min(l_extendedprice) AS lo, max(l_extendedprice) AS hi FROM lineitem), "
    "c AS (SELECT l_orderkey, l_linenumber, lo, (hi - lo) / 255.0::DOUBLE AS step, l_extendedprice AS x FROM lineitem, b) "
    f"SELECT l_orderkey, l_linenumber, {B.code_of('x', 'lo', 'step', 8)} AS code, round(lo + step * {B.code_of('x', 'lo', 'step', 8)}, 6) AS approx FROM c"
)
def scalar_quantize_price(spark, sf_dir):
    rows = io.table(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_extendedprice")
    lo, hi = rows.agg(F.min("l_extendedprice"), F.max("l_extendedprice")).first()
    code = quantize.scalar_code("l_extendedprice", 8, F.lit(lo), F.lit(hi))
    return rows.select("l_orderkey", "l_linenumber", code.alias("code"), F.round(quantize.scalar_decode(code, F.lit(lo), F.lit((hi - lo) / 255.0)), 6).alias("approx"))


@query(f"WITH {B.MEAN} SELECT CAST(j AS INTEGER) AS j, mu FROM mu")
def mean_vector(spark, sf_dir):
    return model.mean_rows(io.base(spark, sf_dir)).select(F.col("j").cast("int").alias("j"), "mu")


@query(f"WITH {B.MEAN} {_cells_sql('cen')}")
def center_vectors(spark, sf_dir):
    db = io.base(spark, sf_dir)
    return _cells(model.centered(db, model.dataset_mean(db)), "vec", "id")


def _pvq(bits: int):
    @query(f"WITH {B.MEAN}, {B.pv(bits)} SELECT id, {B.text_of('codes')} AS codes, round(lo, 9) AS lo, round(step, 9) AS step FROM enc", f"pvq_encode_{bits}")
    def run(spark, sf_dir):
        db = io.base(spark, sf_dir)
        q = model.centered(db, model.dataset_mean(db)).withColumn("q", quantize.pvq("vec", bits))
        return q.select("id", _joined("q.codes").alias("codes"), F.round("q.lo", 9).alias("lo"), F.round("q.step", 9).alias("step"))


for _b in (2, 4, 8):
    _pvq(_b)


@query(f"WITH {B.MEAN}, {B.codec_sql('pv8')} {_cells_sql('dec')}")
def pvq_decode_8(spark, sf_dir):
    return _cells(model.encode(io.base(spark, sf_dir), "pv8"), "vec", "id")


@query(f"WITH {B.MEAN}, {B.pv(4)}, {B.residual(4)} SELECT id, {B.text_of('codes')} AS codes, {B.text_of('codes2')} AS codes2 FROM enc2")
def pvq_residual_4x4(spark, sf_dir):
    db = io.base(spark, sf_dir)
    q = model.centered(db, model.dataset_mean(db)).withColumn("q", quantize.pvq("vec", 4))
    return q.select("id", _joined("q.codes").alias("codes"), _joined(quantize.residual_codes("vec", "q", 4)).alias("codes2"))


@query(f"WITH {B.MEAN}, {B.codec_sql('pv4x8')} {_cells_sql('dec')}")
def pvq_two_level_4x8(spark, sf_dir):
    return _cells(model.encode(io.base(spark, sf_dir), "pv4x8"), "vec", "id")


def _half_sql(x: str) -> str:
    # The exponent of the largest power of two at most |x|, at least -14.
    e = f"greatest(CASE WHEN pow(2.0, floor(log2(abs({x})))) > abs({x}) THEN floor(log2(abs({x}))) - 1 ELSE floor(log2(abs({x}))) END, -14)"
    return f"CASE WHEN {x} = 0 THEN {x} ELSE sign({x}) * (round_even(abs({x}) / pow(2.0, {e} - 10), 0) * pow(2.0, {e} - 10)) END"


@query(f"WITH {B.MEAN}, b AS (SELECT id, list_min(vec) AS lo, list_max(vec) AS hi FROM cen) SELECT id, {_half_sql('lo')} AS lo16, {_half_sql('hi')} AS hi16 FROM b")
def half_precision_bounds(spark, sf_dir):
    db = io.base(spark, sf_dir)
    c = model.centered(db, model.dataset_mean(db))
    return c.select("id", quantize.half_round(F.array_min("vec")).alias("lo16"), quantize.half_round(F.array_max("vec")).alias("hi16"))


@query(
    f"WITH {B.MEAN}, b AS (SELECT id, vec, list_min(vec) AS l, list_max(vec) AS h FROM cen), r AS (SELECT id, vec, {_half_sql('l')} AS lo, {_half_sql('h')} AS hi FROM b), "
    f"e AS (SELECT id, vec, lo, (hi - lo) / 255.0::DOUBLE AS step FROM r) SELECT id, {B.text_of('list_transform(vec, lambda x: ' + B.code_of('x', 'lo', 'step', 8) + ')')} AS codes, round(lo, 9) AS lo, round(step, 9) AS step FROM e"
)
def pvq_encode_8_f16(spark, sf_dir):
    """Constants rounded to half precision before anything is coded by them."""
    db = io.base(spark, sf_dir)
    q = model.centered(db, model.dataset_mean(db)).withColumn("q", quantize.pvq("vec", 8, "f16"))
    return q.select("id", _joined("q.codes").alias("codes"), F.round("q.lo", 9).alias("lo"), F.round("q.step", 9).alias("step"))


@query(
    f"WITH {B.MEAN}, {B.pv(8, 'cen', 'e8')}, {B.pv(4, 'cen', 'e4')} SELECT e8.id, CAST(len(e8.codes) AS BIGINT) AS bytes8, CAST(ceil(len(e4.codes) / 2.0) AS BIGINT) AS bytes4, "
    "CAST(ceil(len(e8.codes) / 32.0) * 32 AS BIGINT) AS padded8 FROM e8 JOIN e4 ON e8.id = e4.id"
)
def packed_size(spark, sf_dir):
    db = io.base(spark, sf_dir)
    c = model.centered(db, model.dataset_mean(db)).select("id", quantize.pvq("vec", 8)["codes"].alias("c8"), quantize.pvq("vec", 4)["codes"].alias("c4"))
    size = lambda p: F.octet_length(p).cast("long")
    return c.select("id", size(pack.pack("c8", 8)).alias("bytes8"), size(pack.pack("c4", 4)).alias("bytes4"), size(pack.pack("c8", 8, 32)).alias("padded8"))


@query(
    f"WITH {B.MEAN}, {B.pv(4)} SELECT id, upper(array_to_string(list_transform(range(0, len(codes) // 2), lambda i: printf('%x', codes[2 * i + 2]) || printf('%x', codes[2 * i + 1])), '')) AS packed FROM enc"
)
def hex_pack(spark, sf_dir):
    db = io.base(spark, sf_dir)
    c = model.centered(db, model.dataset_mean(db))
    return c.select("id", F.hex(pack.pack(quantize.pvq("vec", 4)["codes"], 4)).alias("packed"))


def _pairs(kind: str):
    @query(f"WITH {B.DB} SELECT id, round({B.score('a.vec', 'db.vec', kind)}, 9) AS score FROM db, (SELECT vec FROM q ORDER BY qid LIMIT 1) a", f"sim_{kind}")
    def run(spark, sf_dir):
        """All rows against one query: an expression over the scan."""
        return io.base(spark, sf_dir).select("id", F.round(sim(_first_query(spark, sf_dir), "vec", kind), 9).alias("score"))

    @query(f"WITH {B.DB} SELECT qid, CAST(rank AS INTEGER) AS rank, id, round(score, 6) AS score FROM ({B.knn(kind=kind)})", f"exact_knn_{kind}")
    def search(spark, sf_dir):
        return exact.exact_knn(io.base(spark, sf_dir), io.held_out(spark, sf_dir), 10, kind).withColumn("score", F.round("score", 6))


for _k in ("l2", "ip", "cos"):
    _pairs(_k)


@query(f"WITH {B.MEAN}, {B.codec_sql('pv8')} SELECT qid, CAST(rank AS INTEGER) AS rank, id, round(score, 6) AS score FROM ({B.knn('dec')})")
def asymmetric_knn_8(spark, sf_dir):
    """Distances from codes and two constants, nothing decoded but the finalists."""
    db, q = io.base(spark, sf_dir), io.held_out(spark, sf_dir)
    mean = model.dataset_mean(db)
    coded = model.centered(db, mean).select("id", quantize.pvq("vec", 8).alias("q")).select("id", "q.*")
    return exact.coded_knn(coded, q, 10, mean).select("qid", "rank", "id", F.round("score", 6).alias("score"))


@query(f"WITH {B.MEAN}, {B.codec_sql('pv8')} SELECT dec.id, round({B.score('a.vec', 'dec.vec')}, 6) AS l2, round({B.dot('a.vec', 'dec.vec')}, 6) AS ip FROM dec, (SELECT vec FROM q ORDER BY qid LIMIT 1) a")
def asymmetric_scores(spark, sf_dir):
    """One raw query against all codes, distance and inner product, as expressions over codes and constants."""
    db = io.base(spark, sf_dir)
    mean, one = model.dataset_mean(db), _first_query(spark, sf_dir)
    coded = model.centered(db, mean).select("id", quantize.pvq("vec", 8).alias("q"))
    return coded.select("id", *(F.round(quantize.asym_score(one, "q", mean, kind), 6).alias(kind) for kind in ("l2", "ip")))


def _first_query(spark, sf_dir):
    """The held-out vector of the smallest id, as a constant."""
    return F.array(*(F.lit(float(x)) for x in io.held_out(spark, sf_dir).orderBy("qid").first()["vec"]))


def _knn_of(codec: str, name: str):
    @query(f"WITH {B.MEAN}, {B.codec_sql(codec)} SELECT qid, CAST(rank AS INTEGER) AS rank, id, round(score, 6) AS score FROM ({B.knn('dec')})", name)
    def run(spark, sf_dir):
        return exact.exact_knn(model.encode(io.base(spark, sf_dir), codec), io.held_out(spark, sf_dir), 10).withColumn("score", F.round("score", 6))


@query(
    f"WITH {B.DB}, s AS (SELECT max(list_max(list_transform(vec, lambda x: abs(x)))) / 127.0::DOUBLE AS s FROM db), dec AS (SELECT id, list_transform(vec, lambda x: floor(x / s + 0.5) * s) AS vec FROM db, s) "
    f"SELECT qid, CAST(rank AS INTEGER) AS rank, id, round(score, 6) AS score FROM ({B.knn('dec')})"
)
def low_precision_knn(spark, sf_dir):
    """One symmetric 8-bit scale for all components of all vectors, nothing centered."""
    return exact.exact_knn(model.encode(io.base(spark, sf_dir), "lp8"), io.held_out(spark, sf_dir), 10).withColumn("score", F.round("score", 6))


for _c, _n in (("gl4", "global_quantize_4"), ("gl8", "global_quantize_8"), ("gl4x4", "global_two_level"), ("pd4", "per_dim_quantize_4")):
    _knn_of(_c, _n)


@query(
    f"WITH {B.DB}, h AS (SELECT id, list_transform(vec, lambda x: {_half_sql('x')}) AS vec FROM db) SELECT qid, CAST(rank AS INTEGER) AS rank, id, round(score, 6) AS score FROM ({B.knn('h')})"
)
def float16_knn(spark, sf_dir):
    return exact.exact_knn(model.encode(io.base(spark, sf_dir), "f16"), io.held_out(spark, sf_dir), 10).withColumn("score", F.round("score", 6))


def _fp8_sql(x: str, e: int, m: int) -> str:
    bias = 2 ** (e - 1) - 1
    ex = f"greatest(CASE WHEN pow(2.0, floor(log2(abs({x})))) > abs({x}) THEN floor(log2(abs({x}))) - 1 ELSE floor(log2(abs({x}))) END, {1 - bias})"
    top = 2.0 ** (2**e - 2 - bias) * (2 - 2.0**-m)
    return f"CASE WHEN {x} = 0 THEN {x} ELSE sign({x}) * least(round_even(abs({x}) / pow(2.0, {ex} - {m}), 0) * pow(2.0, {ex} - {m}), {top}) END"


@query(
    f"WITH {B.DB}, a AS (SELECT id, list_transform(vec, lambda x: {_fp8_sql('x', 4, 3)}) AS vec FROM db), b AS (SELECT id, list_transform(vec, lambda x: {_fp8_sql('x', 5, 2)}) AS vec FROM db) "
    f"SELECT 'fp8e4' AS codec, qid, CAST(rank AS INTEGER) AS rank, id, round(score, 6) AS score FROM ({B.knn('a')}) UNION ALL SELECT 'fp8e5', qid, CAST(rank AS INTEGER), id, round(score, 6) FROM ({B.knn('b')})"
)
def fp8_knn(spark, sf_dir):
    db, q = io.base(spark, sf_dir), io.held_out(spark, sf_dir)
    both = [exact.exact_knn(model.encode(db, c), q, 10).select(F.lit(c).alias("codec"), "qid", "rank", "id", F.round("score", 6).alias("score")) for c in ("fp8e4", "fp8e5")]
    return both[0].unionByName(both[1])


def _recall(codec: str, name: str, k: int = 10):
    truth, found = B.knn(k=k), B.knn("dec", k=k)
    codec_ctes = B.codec_sql(codec)

    @query(f"WITH {B.MEAN}, {codec_ctes}, t AS ({truth}), f AS ({found}) SELECT '{codec}' AS codec, round(({B.recall_sql('f', 't')}), 6) AS recall", name)
    def run(spark, sf_dir):
        db, q = io.base(spark, sf_dir), io.held_out(spark, sf_dir)
        got = measures.recall(exact.exact_knn(model.encode(db, codec), q, k), exact.exact_knn(db, q, k), k)
        return got.select(F.lit(codec).alias("codec"), F.round("recall", 6).alias("recall"))


for _c in ("pv2", "pv4", "pv8", "gl4", "gl8", "pd4", "pv4x4", "pv8x8"):
    _recall(_c, f"recall_{_c}")
_recall("pv8", "recall_100_pv8", 100)
_recall("pv4", "recall_750", 750)


@query(
    f"WITH {B.MEAN}, {B.codec_sql('pv4', 'one')}, {B.codec_sql('pv4x8', 'two')}, beam AS ({B.knn('one', k=40)}), "
    f"s AS (SELECT beam.qid, beam.id, {B.score('q.vec', 'two.vec')} AS score FROM beam JOIN q ON q.qid = beam.qid JOIN two ON two.id = beam.id) "
    "SELECT qid, CAST(row_number() OVER (PARTITION BY qid ORDER BY score DESC, id) AS INTEGER) AS rank, id, round(score, 6) AS score FROM s QUALIFY rank <= 10"
)
def rerank_exhaustive_4x8(spark, sf_dir):
    """Shortlist by the first level, then both levels for the shortlist only."""
    return _rerank(spark, sf_dir, 8)


@query(
    f"WITH {B.MEAN}, {B.codec_sql('pv4', 'one')}, {B.codec_sql('pv4x4', 'two')}, beam AS ({B.knn('one', k=40)}), "
    f"s AS (SELECT beam.qid, beam.id, {B.score('q.vec', 'two.vec')} AS score FROM beam JOIN q ON q.qid = beam.qid JOIN two ON two.id = beam.id) "
    "SELECT qid, CAST(row_number() OVER (PARTITION BY qid ORDER BY score DESC, id) AS INTEGER) AS rank, id, round(score, 6) AS score FROM s QUALIFY rank <= 10"
)
def rerank_exhaustive_4x4(spark, sf_dir):
    return _rerank(spark, sf_dir, 4)


def _rerank(spark, sf_dir, bits2):
    db, q = io.base(spark, sf_dir), io.held_out(spark, sf_dir)
    mean = model.dataset_mean(db)
    coded = model.centered(db, mean).withColumn("q", quantize.pvq("vec", 4))
    levels = coded.select("id", "q", quantize.residual_codes("vec", "q", bits2).alias("r"))
    first = coded.select("id", center(quantize.decode("q"), [-m for m in mean]).alias("vec"))
    beam = exact.exact_knn(first, q, 40).select("qid", "id")
    # Only finalists read the second level.
    final = beam.join(levels, "id").join(F.broadcast(q.withColumnRenamed("vec", "qvec")), "qid")
    scored = final.select("qid", "id", sim("qvec", center(quantize.decode2("q", "r", bits2), [-m for m in mean])).alias("score"))
    return exact.topk(scored, 10).select("qid", "rank", "id", F.round("score", 6).alias("score"))


@query(f"WITH {B.EMB} SELECT id, CAST(unnest(range(0, len(vec))) AS INTEGER) AS j, round(unnest(list_transform(vec, lambda x: x / n)), 9) AS x FROM (SELECT id, vec, sqrt({B.dot('vec', 'vec')}) AS n FROM emb) WHERE n > 0")
def normalize_vectors(spark, sf_dir):
    v = io.vectors(spark, sf_dir).select("id", normalize("vec").alias("vec")).where("vec is not null")
    return v.select("id", F.posexplode("vec").alias("j", "x")).withColumn("x", F.round("x", 9))


@query(
    f"WITH {B.MEAN}, m0 AS (SELECT id FROM db, mean ORDER BY {B.sq_l2('vec', 'm')}, id LIMIT 1) SELECT id FROM m0"
)
def entry_point(spark, sf_dir):
    db = io.base(spark, sf_dir)
    mu = F.array(*(F.lit(m) for m in model.dataset_mean(db)))
    return db.agg(F.min_by("id", F.struct(sq_l2("vec", mu), F.col("id"))).alias("id"))


@query(f"WITH {B.DB} SELECT id, round({B.dot('vec', 'vec')}, 9) AS squares, round({B.fold('vec[i]', 'vec')}, 9) AS total, round(sqrt({B.dot('vec', 'vec')}), 9) AS length FROM db")
def dot_norm_battery(spark, sf_dir):
    return io.base(spark, sf_dir).select("id", F.round(dot("vec", "vec"), 9).alias("squares"), F.round(total("vec"), 9).alias("total"), F.round(norm("vec"), 9).alias("length"))
