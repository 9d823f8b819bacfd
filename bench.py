"""Headline queries, timed: prints one JSON line.

BENCH_SF_DIR (default /root/testdata/sf0.1) and BENCH_CPUS (default 8) set the
tables and the cores. Every query runs once to warm up, then BENCH_REPS times
(default 1); the best time counts, and ``recall`` and ``qps`` tell what the
graph searches reached. ``kernel_*`` and ``scaling`` hold the measures of time:
by codec, window, mode, ablation and number of tasks.
"""

from __future__ import annotations

import json
import os
import time

import numpy as np
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from vecengine import registry
from vecengine.operators import exact, measures, shard
from vecengine.sources import embed, io

HEADLINE = ("exact_knn_l2", "recall_pv8", "recall_pv4x4", "asymmetric_knn_8", "rerank_exhaustive_4x8", "knn_graph_exact", "prune_alpha12", "graph_search_beam", "ivf_flat_all_probe", "pq_rerank_knn", "hash_embed_docs", "asof_last_event")


def graph_figures(spark: SparkSession, sf_dir: str) -> dict:
    """Recall and queries a second of the batch search, by codec, on one built graph each."""
    db, q = io.base(spark, sf_dir), io.held_out(spark, sf_dir)
    truth, out = io.staged(exact.exact_knn(db, q, 10), "truth"), {}
    for codec in ("f32", "f16", "pv8", "pv4x8"):
        index = io.staged(shard.build_index(db.withColumn("shard", F.lit(0)), codec, 32, 64), "index")
        shard.search_index(index, q, 10, 60, rerank="x" in codec).count()
        began = time.time()
        found = io.staged(shard.search_index(index, q, 10, 60, rerank="x" in codec), "found")
        took = time.time() - began
        out[codec] = {"recall": round(measures.recall(found, truth, 10).first()["recall"], 4), "qps": round(q.count() / took, 1)}
    return out


def best_of(reps: int, run) -> float:
    took = []
    for _ in range(reps):
        began = time.perf_counter()
        run()
        took.append(time.perf_counter() - began)
    return min(took)


def kernel_figures(spark: SparkSession, sf_dir: str, d: int, queries: int = 200, reps: int = 5) -> dict:
    """Search in one thread on one built graph of hashed texts, best of ``reps``, by codec.

    For each: recall and queries a second by window, queries a second at recall
    0.9 (on the line between the windows around it), one query at a time,
    microseconds and bytes a second of scoring, and megabytes of codes and
    graph. ``ablation``: the visited set and the number of queries that move together.
    """
    docs = embed.hash_embed(io.table(spark, sf_dir, "documents"), d, "doc_id", "text").orderBy("id").toPandas()
    x = np.stack(docs["vec"].to_numpy())
    x, q = x[np.arange(len(x)) % 25 != 0], x[::25][:queries]
    truth = np.argsort((x * x).sum(1) - 2 * (q @ x.T), axis=1)[:, :10]
    built = shard.Graph(shard.Codes.of(x, "pv8"), 16).build(32, (1.2,))
    out: dict = {"n": len(x)}
    for codec in ("f32", "f16", "pv8", "pv4x8"):
        g = shard.Graph(shard.Codes.of(x, codec), 16, "l2", built.entry, built.nbrs)
        rows, again = [], "x" in codec
        for w in (10, 20, 40, 80):
            found, _, _, evals = g.search(q, 10, w, rerank=again)
            recall = np.mean([len(set(a) & set(b)) / 10 for a, b in zip(found.tolist(), truth.tolist(), strict=True)])
            rows.append((w, round(float(recall), 4), round(len(q) / best_of(reps, lambda w=w, g=g, again=again: g.search(q, 10, w, rerank=again)), 1), float(evals.mean())))
        at = next((round(a[2] + (b[2] - a[2]) * (0.9 - a[1]) / max(b[1] - a[1], 1e-9), 1) for a, b in zip(rows, rows[1:], strict=False) if a[1] <= 0.9 <= b[1]), None)
        one, rng = g.codes.scorer(q, "l2"), np.random.default_rng(1)
        who, where = rng.integers(0, len(q), 20_000), rng.integers(0, len(x), 20_000)
        each = best_of(reps, lambda one=one, who=who, where=where: one(who, where)) / len(where)
        raw = g.codes.x if g.codes.x is not None else g.codes.first
        single = best_of(2, lambda g=g, again=again: [g.search(q[i : i + 1], 10, 40, rerank=again) for i in range(20)])
        out[codec] = {"by_window": [r[:3] for r in rows], "qps_at_0.9": at, "qps_single": round(20 / single, 1), "score_us": round(each * 1e6, 4), "gb_s": round(raw[0].nbytes / each / 1e9, 3), "mb": round((raw.nbytes + g.nbrs.nbytes) / 1e6, 2)}
    g = shard.Graph(shard.Codes.of(x, "pv8"), 16, "l2", built.entry, built.nbrs)
    out["ablation"] = {"visited": round(len(q) / best_of(3, lambda: g.search(q, 10, 40, visited=True)), 1), "no_visited": round(len(q) / best_of(3, lambda: g.search(q, 10, 40)), 1)}
    for batch in (8, 64):
        out["ablation"][f"batch_{batch}"] = round(len(q) / best_of(3, lambda batch=batch: [g.search(q[i : i + batch], 10, 40) for i in range(0, len(q), batch)]), 1)
    carried = shard.Graph(g.codes, 16, "l2", built.entry, built.nbrs).carry()
    out["ablation"]["carried_codes"] = round(len(q) / best_of(3, lambda: carried.search(q, 10, 40)), 1)
    return out


def scaling_figures(spark: SparkSession, sf_dir: str, cpus: int) -> dict:
    """Seconds of one exact search over the same rows in 1, 2, 4, .. tasks, and megabytes scanned a second."""
    db, q = io.staged(io.base(spark, sf_dir), "scaling"), io.held_out(spark, sf_dir)
    many = io.staged(db.crossJoin(spark.range(20).withColumnRenamed("id", "copy")).select((F.col("id") * 20 + F.col("copy")).alias("id"), "vec"), "scaling")
    out, tasks, size = {}, 1, many.count() * 64 * 8 / 1e6
    while tasks <= cpus:
        dealt = io.staged(many.repartition(tasks), "scaling")
        took = best_of(2, lambda dealt=dealt: exact.exact_knn(dealt, q, 10).write.format("noop").mode("overwrite").save())
        out[str(tasks)] = {"sec": round(took, 3), "mb_s": round(size / took, 1)}
        tasks *= 2
    return out


def main() -> None:
    sf_dir, cpus, reps = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "8"), int(os.environ.get("BENCH_REPS", "1"))
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").appName("bench").config("spark.sql.shuffle.partitions", cpus)
        .config("spark.driver.memory", "8g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    times = {}
    for name in HEADLINE:
        best = float("inf")
        for rep in range(reps + 1):
            began = time.time()
            registry.QUERIES[name](spark, sf_dir).write.format("noop").mode("overwrite").save()
            best = min(best, time.time() - began) if rep or not reps else best
        times[name] = round(best, 3)
    figures = graph_figures(spark, sf_dir)
    figures = {"graph": figures, "kernel_96": kernel_figures(spark, sf_dir, 96), "kernel_768": kernel_figures(spark, sf_dir, 768), "scaling": scaling_figures(spark, sf_dir, int(cpus))}
    print(json.dumps({"metric": "headline_total", "value": round(sum(times.values()), 3), "unit": "sec", "queries": times, "sf": os.path.basename(sf_dir.rstrip("/")).removeprefix("sf"), **figures}))


if __name__ == "__main__":
    main()
