import tracemalloc

import numpy as np
import pytest


from vecengine.operators import exact, graph, measures, pq, shard
from vecengine.plans import planner


def frame(spark, x, key="id"):
    return spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], f"{key} long, vec array<double>")


@pytest.fixture(scope="module")
def data():
    rng = np.random.default_rng(3)
    return rng.normal(size=(200, 16)), rng.normal(size=(10, 16))


def brute(x, q, k):
    far = np.linalg.norm(q[:, None] - x, axis=2)
    return np.argsort(far, axis=1, kind="stable")[:, :k]


def test_exact_search_against_brute_force_and_in_blocks(spark, data, monkeypatch):
    x, q = data
    db, asks = frame(spark, x), frame(spark, q, "qid")
    want = {(i, int(j)) for i, row in enumerate(brute(x, q, 5)) for j in row}
    assert {(r["qid"], r["id"]) for r in exact.exact_knn(db, asks, 5).collect()} == want
    monkeypatch.setattr(exact, "BROADCAST_BYTES", 0)
    assert {(r["qid"], r["id"]) for r in exact.exact_knn(db, asks, 5).collect()} == want
    assert exact.exact_knn(db, asks, 500).where("qid = 0").count() == 200
    assert exact.exact_knn(db, asks.where("false"), 5).count() == 0


@pytest.mark.parametrize("kind", ["l2", "ip", "cos"])
def test_exact_search_takes_the_smallest_of_many_equal_rows(kind):
    rng = np.random.default_rng(6)
    x = np.concatenate((np.tile(rng.normal(size=16), (3000, 1)), rng.normal(size=(1000, 16)) * 0.01))
    ids = rng.permutation(len(x))
    _, got, score = exact._block_best(ids, x, np.array([7]), x[:1] * 1.1, 5, kind)
    assert got.tolist() == sorted(ids[:3000])[:5] and len(set(score)) == 1


@pytest.mark.parametrize("kind", ["l2", "ip", "cos"])
def test_exact_search_holds_few_scores_at_once(kind):
    rng = np.random.default_rng(8)
    x, q, k = np.round(rng.normal(size=(6000, 4)), 1), np.round(rng.normal(size=(3000, 4)), 1), 45
    x[17], q[5] = np.nan, np.inf
    tracemalloc.start()
    qids, ids, score = exact._block_best(np.arange(len(x)), x, np.arange(len(q)), q, k, kind)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 120e6  # all scores of the block are 144 MB
    for i in (0, 1, 2999):
        own = -np.sqrt(((x - q[i]) ** 2).sum(1)) if kind == "l2" else (x * q[i]).sum(1) if kind == "ip" else (x / np.linalg.norm(x, axis=1, keepdims=True) * (q[i] / np.linalg.norm(q[i]))).sum(1)
        best = np.lexsort((np.arange(len(x)), np.where(np.isfinite(own), -own, np.inf)))[:k]
        assert ids[qids == i].tolist() == best.tolist() and np.array_equal(score[qids == i], own[best])
    assert not (qids == 5).any() and not (ids == 17).any()


def test_many_answers_are_found_in_a_grid(spark, data, monkeypatch):
    x, _ = data
    db = frame(spark, x)
    want = graph.knn_candidates(db, 7).orderBy("src", "rank").collect()
    monkeypatch.setattr(exact, "ANSWERS", 100)
    monkeypatch.setattr(exact, "QUERY_BLOCK", 64)
    monkeypatch.setattr(exact, "ROW_BYTES", 90 * 16 * 8)
    monkeypatch.setattr(exact, "CELLS", 500)
    assert graph.knn_candidates(db, 7).orderBy("src", "rank").collect() == want


def test_pruning_example_and_cap(spark):
    db = spark.createDataFrame([(0, [0.0, 0.0]), (1, [1.0, 0.0]), (2, [2.0, 0.0]), (3, [0.0, 3.0])], "id long, vec array<double>")
    cands = graph.knn_candidates(db, 3).where("src = 0")
    assert [r["id"] for r in graph.prune(cands, db, 1.0, 2).orderBy("pos").collect()] == [1, 3]
    assert [r["id"] for r in graph.prune(cands, db, 1.0, 1).collect()] == [1]


def test_graph_full_window_is_exact_degrees_hold_and_visited_does_not_matter(data):
    x, q = data
    g = shard.Graph(shard.Codes.of(x, "f32"), 8).build(16)
    assert g.nbrs.max() < len(x) and not (g.nbrs == np.arange(len(x))[:, None]).any()
    assert all(len(set(r[r >= 0])) == (r >= 0).sum() for r in g.nbrs)
    full, *_ = g.search(q, 5, len(x))
    assert (full == brute(x.astype(np.float32), q, 5)).all()
    a, b = g.search(q, 5, 20), g.search(q, 5, 20, visited=True)
    assert (a[0] == b[0]).all() and (a[3] >= b[3]).all()
    hits = [np.mean([len(set(g.search(q, 5, w)[0][i]) & set(full[i])) for i in range(len(q))]) for w in (5, 10, 40)]
    assert hits[0] <= hits[1] + 1e-9 <= hits[2] + 2e-9


@pytest.mark.parametrize(("codec", "kind"), [("f32", "l2"), ("pv8", "l2"), ("pv8", "ip"), ("pv4x8", "l2"), ("gl8", "ip"), ("f16", "l2"), ("pq8", "l2"), ("pq8", "ip")])
def test_scores_from_codes_equal_those_of_decoded_rows(data, codec, kind):
    x, q = data
    codes = shard.Codes.of(x, codec)
    at, rows = np.repeat(np.arange(len(q)), 50), np.tile(np.arange(50), len(q))
    want = shard.score(q, codes.rows(np.broadcast_to(np.arange(50), (len(q), 50))), kind)
    assert np.allclose(codes.scorer(q, kind)(at, rows).reshape(len(q), -1), want, atol=2e-4)


def test_heaps_and_carried_codes_give_the_same_answers(data):
    x, q = data
    g = shard.Graph(shard.Codes.of(x, "pv8"), 8).build(16)
    ids, *_ = g.search(q, 5, 20)
    assert all(g.search_heap(one, 5, 20)[0].tolist() == row for one, row in zip(q, ids.tolist(), strict=True))
    carried = shard.Graph(g.codes, 8, "l2", g.entry, g.nbrs).carry()
    assert (carried.search(q, 5, 20)[0] == ids).all()
    assert (np.concatenate([g.search(q[i : i + 1], 5, 20)[0] for i in range(len(q))]) == ids).all()


def test_index_in_shards_blocks_of_queries_and_look_ups(spark, data, monkeypatch):
    x, q = data
    db, asks = planner.deal(frame(spark, x), len(x), 16, 60), frame(spark, q, "qid")
    assert db.select("shard").distinct().count() == 4
    index = shard.build_index(db, "pv8", 8, 16, mean=x.mean(axis=0).tolist()).persist()
    one = shard.search_index(index, asks, 5, 60).orderBy("qid", "rank").collect()
    hits = np.mean([[r["id"] for r in one if r["qid"] == i][0] in row for i, row in enumerate(brute(x, q, 2).tolist())])
    assert hits >= 0.9
    monkeypatch.setattr(shard, "BROADCAST_BYTES", 400)
    assert shard.search_index(index, asks, 5, 60).orderBy("qid", "rank").collect() == one
    assert shard.search_index(index, asks.where("false"), 5, 60).count() == 0
    coded = shard.search_index(shard.build_index(db, "f32", 8, 16, search_codec="pq16"), asks, 5, 60)
    assert coded.count() == 50
    monkeypatch.undo()
    layers = shard.search_layers(db, asks, 5, (10, 60), 8, 32)
    assert measures.recall(layers.where("window = 60"), exact.exact_knn(db, asks, 5), 5).first()[0] >= 0.9


def test_reaches_beyond_many_hops_and_ends_every_query(spark):
    chain = spark.createDataFrame([(i, i + 1) for i in range(80)], "src long, id long")
    assert graph.reachable(chain, [0]).count() == 81
    db = spark.createDataFrame([(i, [float(i), 0.0]) for i in range(9)], "id long, vec array<double>")
    q = spark.createDataFrame([(0, [8.0, 0.0]), (1, [3.2, 0.0])], "qid long, vec array<double>")
    got = graph.graph_search_rounds(chain.where("id < 9"), db, q, 1, 2, [0]).orderBy("qid").collect()
    assert [r["id"] for r in got] == [8, 3]


def test_scan_by_codes_equals_the_decoded_scan(spark, data, monkeypatch):
    from vecengine.functions import quantize

    x, q = data
    db, asks = frame(spark, x), frame(spark, q, "qid")
    mean = [0.1] * 16
    coded = db.select("id", quantize.pvq(quantize.F.transform("vec", lambda v: v - 0.1), 8).alias("q")).select("id", "q.*")
    plain = coded.select("id", quantize.F.transform(quantize.decode(quantize.F.struct("codes", "lo", "step")), lambda v: v + 0.1).alias("vec"))
    want = [(r["qid"], r["rank"], r["id"]) for r in exact.exact_knn(plain, asks, 7).orderBy("qid", "rank").collect()]
    for size in (exact.BROADCAST_BYTES, 400):
        monkeypatch.setattr(exact, "BROADCAST_BYTES", size)
        assert [(r["qid"], r["rank"], r["id"]) for r in exact.coded_knn(coded, asks, 7, mean).orderBy("qid", "rank").collect()] == want


def test_encoders_are_not_copied_into_filters(spark, data):
    from vecengine.operators import model

    plan = exact.exact_knn(model.encode(frame(spark, data[0]), "pv4x4"), frame(spark, data[1], "qid"), 5)._jdf.queryExecution().optimizedPlan().toString()
    assert "Filter" not in plan.split("MapInArrow")[-1]


def test_late_rows_drop_out_of_a_stream(spark, tmp_path):
    from vecengine.streaming import flows

    for i, rows in enumerate(([("2024-01-01 10:00:00", 1.0), ("2024-01-03 00:00:00", 1.0)], [("2024-01-03 00:10:00", 1.0)], [("2024-01-01 10:30:00", 1.0)], [("2024-01-04 00:00:00", 1.0)])):
        spark.createDataFrame([(t, "view", v) for t, v in rows], "ts string, event_type string, value double").coalesce(1).write.parquet(f"{tmp_path}/{i}")
    s = spark.readStream.schema("ts string, event_type string, value double").option("maxFilesPerTrigger", 1).option("recursiveFileLookup", "true").parquet(str(tmp_path))
    done = flows.drain(spark, flows.windowed_counts(s, "1 hour", late="1 hour"), "late_rows", "append")
    # The row of 10:30 comes when its window is closed already.
    assert done.where("start = timestamp '2024-01-01 10:00:00'").groupBy().sum("n").first()[0] == 1


def test_inner_product_pruning_ends(data):
    x, q = data
    g = shard.Graph(shard.Codes.of(x, "pv8"), 8, "ip").build(16, (1.0, 0.95))
    assert g.search(q, 3, 20)[0].min() >= 0


def test_rounds_and_shard_agree(spark, data):
    x, q = data[0][:80], data[1][:3]
    g = shard.Graph(shard.Codes.of(x, "f32"), 6).build(12)
    src, pos = np.nonzero(g.nbrs >= 0)
    edges = spark.createDataFrame([(int(s), int(g.nbrs[s, p])) for s, p in zip(src, pos, strict=True)], "src long, id long")
    db = frame(spark, x.astype(np.float32).astype(float))
    got = graph.graph_search_rounds(edges, db, frame(spark, q, "qid"), 4, 8, [g.entry]).orderBy("qid", "rank").collect()
    ids, _, hops, evals = g.search(q, 4, 8)
    assert [r["id"] for r in got] == ids.ravel().tolist()
    assert {r["qid"]: (r["hops"], r["evals"]) for r in got} == {i: (hops[i], evals[i]) for i in range(3)}


def test_recall_and_rank_overlap(spark):
    truth = spark.createDataFrame([(0, r, r) for r in range(1, 11)], "qid long, rank int, id long")
    found = spark.createDataFrame([(0, r, r if r < 10 else 11) for r in range(1, 11)], "qid long, rank int, id long")
    assert measures.recall(found, truth, 10).first()[0] == 0.9
    same = measures.rbo(truth, truth, 10).first()
    assert abs(same["rbo_ext"] - 1) < 1e-9
    a, b = measures.rbo(truth, found, 10).first()["rbo"], measures.rbo(found, truth, 10).first()["rbo"]
    assert abs(a - b) < 1e-12 and 0 < a < same["rbo"]


def test_inverted_file_with_all_cells_is_exact(spark, data):
    x, q = data
    index = pq.ivf_build(frame(spark, x), 4)
    got = {(r["qid"], r["id"]) for r in pq.ivf_search(index, frame(spark, q, "qid"), 5, 4).collect()}
    assert got == {(i, int(j)) for i, row in enumerate(brute(x, q, 5)) for j in row}


def test_rotation_does_not_hurt_and_reverse_edges_are_capped(spark, data):
    x, _ = data
    loss = [((x - c.decode(c.encode(x))[:, :16]) ** 2).sum() for c in (pq.train(x, 4, 16), pq.train(x, 4, 16, rotate=3))]
    assert loss[1] < loss[0] * 1.05
    hub = spark.createDataFrame([(i, 0, -float(i)) for i in range(1, 30)], "src long, id long, score double")
    kept = graph.add_reverse(hub, 5).where("src = 0").select("id").toPandas()["id"].tolist()
    assert sorted(kept) == [1, 2, 3, 4, 5]


def test_plan_choices():
    assert planner.plan(1000, 64).method == "scan" and planner.plan(10**9, 96).degree == 128
    assert planner.plan(10**7, 768).codec == "pv4x8" and planner.defaults(10, "ip")[1] == (1.0, 0.95)


def test_scan_reads_needed_columns_only(spark):
    from vecengine.workloads.relational import scan_embeddings

    plan = scan_embeddings(spark, "/root/testdata/sf0.001")._jdf.queryExecution().toString()
    assert "PushedFilters" in plan and "embedding#" not in plan.split("== Physical Plan ==")[1]
