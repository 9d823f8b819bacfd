"""Pruning and neighbour lists as DataFrame operations."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from vecengine.functions.vectors import dot, sim, sq_l2
from vecengine.operators.exact import exact_knn, topk


def knn_candidates(db: DataFrame, kappa: int, kind: str = "l2") -> DataFrame:
    """(src, rank, id, score): the kappa nearest others of every row, by exhaustive scan."""
    found = exact_knn(db, db.select(F.col("id").alias("qid"), "vec"), kappa + 1, kind).where("qid <> id")
    return topk(found.select("qid", "id", "score"), kappa).select(F.col("qid").alias("src"), "rank", "id", "score")


def prune_fold(cands, alpha: float, degree: int, kind: str = "l2") -> Column:
    """Kept candidates of an array<struct<score, id, vec>> in order of falling score.

    One pass from the nearest on: a candidate stays unless some kept one s has
    alpha * sim(s, it) >= its own score, and while fewer than ``degree`` are
    kept. For distances, with unsquared negative scores, alpha above 1 keeps
    more; for inner products alpha below 1 does.
    """
    def score(a, b):
        return -F.sqrt(sq_l2(a, b)) if kind == "l2" else dot(a, b)

    def step(kept, c):
        covered = F.exists(kept, lambda s: F.lit(float(alpha)) * score(s["vec"], c["vec"]) >= c["score"])
        return F.when((F.size(kept) >= degree) | covered, kept).otherwise(F.array_append(kept, c))

    empty = F.filter(cands, lambda _: F.lit(False))
    return F.aggregate(cands, empty, step)


def prune(cands: DataFrame, db: DataFrame, alpha: float, degree: int, kind: str = "l2") -> DataFrame:
    """(src, pos, id): out-neighbours from candidates (src, id, score); a vertex is no neighbour of its own."""
    ordered = cands.where("src <> id").join(db, "id").groupBy("src").agg(
        F.sort_array(F.collect_list(F.struct((-F.col("score")).alias("far"), F.col("id"), F.col("score"), F.col("vec")))).alias("c")
    )
    shaped = F.transform("c", lambda x: F.struct(x["score"].alias("score"), x["id"].alias("id"), x["vec"].alias("vec")))
    kept = ordered.select("src", prune_fold(shaped, alpha, degree, kind).alias("kept"))
    return kept.select("src", F.posexplode(F.transform("kept", lambda x: x["id"])).alias("pos", "id"))


def add_reverse(edges: DataFrame, cap: int | None = None, salts: int = 8) -> DataFrame:
    """(src, id): edges and their reverses, repeated ones once.

    With ``cap`` each source keeps its first ``cap`` by (score, id) if the edges
    have scores; taken first in salted parts, so that a hub is not one task's.
    """
    keep = ["score"] if "score" in edges.columns else []
    back = edges.select(F.col("id").alias("src"), F.col("src").alias("id"), *keep)
    both = edges.select("src", "id", *keep).union(back).dropDuplicates(["src", "id"])
    if cap is None:
        return both
    order = [F.desc("score"), "id"] if keep else ["id"]
    salted = both.withColumn("salt", F.pmod(F.xxhash64("id"), F.lit(salts)))
    first = salted.withColumn("r", F.row_number().over(Window.partitionBy("src", "salt").orderBy(*order))).where(F.col("r") <= cap)
    return first.withColumn("r", F.row_number().over(Window.partitionBy("src").orderBy(*order))).where(F.col("r") <= cap).drop("r", "salt")


def adjacency(edges: DataFrame) -> DataFrame:
    return edges.groupBy("src").agg(F.array_sort(F.collect_list("id")).alias("nbrs"))


def bisector_margin(x, xs, xp) -> Column:
    """Signed side of x' against the bisector of x and x*: negative on the side of x*, which means 'prune'."""
    # a = x - x*, b half the difference of squares: a.x' - b.
    a = F.zip_with(xs, x, lambda s, o: o - s)
    return dot(a, xp) - (dot(x, x) - dot(xs, xs)) / 2


def reachable(edges: DataFrame, start: list[int]) -> DataFrame:
    """(id, hops) from the entries on, breadth first, until nothing is new."""
    from vecengine.sources.io import staged

    spark = edges.sparkSession
    seen = spark.createDataFrame([(int(s), 0) for s in start], "id long, hops int")
    front, hop = seen, 0
    while True:
        hop += 1
        step = edges.join(front.select(F.col("id").alias("src")), "src").select("id").distinct()
        front = staged(step.join(seen, "id", "left_anti").withColumn("hops", F.lit(hop)), "reach")
        if not front.limit(1).count():
            break
        seen = staged(seen.union(front), "seen")
    return seen


def degree_stats(edges: DataFrame) -> DataFrame:
    return edges.groupBy("src").agg(F.count("*").alias("degree")).groupBy("degree").agg(F.count("*").alias("vertices"))


def graph_search_rounds(edges: DataFrame, db: DataFrame, q: DataFrame, k: int, window: int, entry: list[int], kind: str = "l2", track_visited: bool = False) -> DataFrame:
    """Greedy search on one global graph, all queries a round at a time.

    The beam of each query is one array, ordered by (score, id), cut to
    ``window``. A round expands the best unexplored vertex of every query that
    still has one; finished queries leave the loop, which ends with the last. Vertices join their edges
    and vectors by id, so only the beams move. Returns (qid, rank, id, score,
    hops, evals). ``track_visited`` remembers all scored ids: the answers are
    the same, and evals counts fewer.
    """
    from vecengine.sources.io import staged

    spark = q.sparkSession
    ids = spark.createDataFrame([(int(e),) for e in entry], "id long")
    seeds = ids.join(db, "id")  # as few rows as entries
    start = q.select("qid", F.col("vec").alias("qvec")).crossJoin(F.broadcast(seeds)).select("qid", "qvec", F.struct((-sim("qvec", "vec", kind)).alias("far"), F.col("id"), F.lit(False).alias("done")).alias("c"))
    beam = start.groupBy("qid").agg(F.first("qvec").alias("qvec"), F.slice(F.sort_array(F.collect_list("c")), 1, window).alias("beam"), F.count("*").alias("evals"))
    visited = F.transform("beam", lambda c: c["id"]) if track_visited else F.array().cast("array<bigint>")
    state = staged(beam.select("qid", "qvec", "beam", F.lit(0).alias("hops"), "evals", visited.alias("visited")), "beams")
    finished = []
    nbrs = staged(adjacency(edges), "adjacency")
    while True:
        over = state.where(~F.exists("beam", lambda c: ~c["done"]))
        if over.limit(1).count():
            finished.append(staged(over.select("qid", "hops", "evals", F.slice("beam", 1, k).alias("best")), "beams-done"))
        if len(finished) > 32:  # keeps the last plan short
            finished = [staged(reduce(DataFrame.unionByName, finished), "beams-done")]
        live = state.where(F.exists("beam", lambda c: ~c["done"]))
        if not live.limit(1).count():
            break
        pick = F.filter("beam", lambda c: ~c["done"])[0]["id"]
        live = live.withColumn("pick", pick)
        live = live.withColumn("beam", F.transform("beam", lambda c: F.struct(c["far"].alias("far"), c["id"].alias("id"), (c["done"] | (c["id"] == F.col("pick"))).alias("done"))))
        known = F.array_union(F.transform("beam", lambda c: c["id"]), F.col("visited"))
        new = live.join(nbrs, live.pick == nbrs.src, "left").select("qid", "qvec", F.explode(F.array_except(F.coalesce("nbrs", F.array().cast("array<bigint>")), known)).alias("id"))
        scored = new.join(db, "id").select("qid", F.struct((-sim("qvec", "vec", kind)).alias("far"), F.col("id"), F.lit(False).alias("done")).alias("c"))
        got = scored.groupBy("qid").agg(F.collect_list("c").alias("new"))
        none = F.filter("beam", lambda _: F.lit(False))
        merged = live.join(got, "qid", "left").withColumn("new", F.coalesce("new", none))
        seen = F.array_union(F.col("visited"), F.transform("new", lambda c: c["id"])) if track_visited else F.col("visited")
        state = staged(
            merged.select("qid", "qvec", F.slice(F.sort_array(F.concat("beam", "new")), 1, window).alias("beam"), (F.col("hops") + 1).alias("hops"), (F.col("evals") + F.size("new")).alias("evals"), seen.alias("visited")),
            "beams",
        )
    if not finished:
        return spark.createDataFrame([], "qid long, rank int, id long, score double, hops int, evals long")
    top = reduce(DataFrame.unionByName, finished).select("qid", "hops", "evals", F.posexplode("best").alias("r", "c"))
    return top.select("qid", (F.col("r") + 1).alias("rank"), F.col("c.id").alias("id"), (-F.col("c.far")).alias("score"), "hops", "evals")
