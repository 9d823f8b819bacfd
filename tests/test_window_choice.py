import numpy as np

from vecengine.operators import shard
from vecengine.plans import planner


def _rows(n: int, d: int = 8) -> np.ndarray:
    x = np.random.default_rng(3).normal(size=(n, d))
    x[::7] = x[0]
    return x


def _kept(g: shard.Graph, src: int, cands, alpha: float) -> list[int]:
    """Pruning of one source, one candidate at a time."""
    x = g.codes.rows(np.arange(len(g.codes))).astype(np.float32)
    own = {c: shard.score(x[[src]], x[[c]][None], g.kind)[0, 0] for c in set(cands) - {-1, src}}
    left, kept = sorted(own, key=lambda c: (-own[c], c)), []
    while left and len(kept) < g.degree:
        best = left.pop(0)
        kept.append(best)
        left = [c for c in left if not alpha * shard.score(x[[best]], x[[c]][None], g.kind)[0, 0] >= own[c]]
    return kept + [-1] * (g.degree - len(kept))


def test_pruning_keeps_what_one_by_one_does_with_ties_among_copies():
    rng = np.random.default_rng(5)
    for kind, alphas, scale in (("l2", (1.0, 1.2), 1.0), ("ip", (1.0, 0.95), 30.0)):
        g = shard.Graph(shard.Codes.of(_rows(200) * scale, "pv8"), 6, kind)
        src = np.arange(0, 200, 5)
        cands = np.where(rng.random((len(src), 300)) < rng.random((len(src), 1)), rng.integers(-1, 200, (len(src), 300)), -1)
        for alpha in alphas:
            assert g.prune(src, cands, alpha).tolist() == [_kept(g, s, c, alpha) for s, c in zip(src.tolist(), cands.tolist(), strict=True)]


def test_reverse_edges_are_linked_without_a_call_for_each_vertex(monkeypatch):
    monkeypatch.setattr(np, "isin", None)
    g = shard.Graph(shard.Codes.of(np.random.default_rng(1).normal(size=(300, 8)), "f32"), 6).build(12)
    ids, *_ = g.search(g.codes.rows(np.arange(300)), 1, 300)
    # A few vertices that no other keeps are out of reach, at any window.
    assert (ids[:, 0] == np.arange(300)).mean() > 0.95
    for row in g.nbrs.tolist():
        some = [v for v in row if v >= 0]
        assert len(some) == len(set(some)) and row[: len(some)] == some


def test_a_beam_skips_what_it_holds_and_scores_again_what_left_it():
    g = shard.Graph(shard.Codes.of(np.random.default_rng(1).normal(size=(400, 8)), "f32"), 6).build(12)
    q = np.random.default_rng(2).normal(size=(20, 8))
    for window in (3, 10, 40):
        beam, every = g.search(q, 3, window), g.search(q, 3, window, visited=True)
        assert (beam[0] == every[0]).all() and (beam[2] == every[2]).all() and (beam[3] >= every[3]).all()
        assert all((g.search_heap(one, 3, window)[0] == ids).all() for one, ids in zip(q, beam[0], strict=True))


def test_tasks_share_the_queries_of_a_shard(spark, monkeypatch):
    x = _rows(700)
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "id long, vec array<double>")
    db, q = df.where("id < 100"), df.withColumnRenamed("id", "qid")
    index = shard.staged(shard.build_index(planner.deal(db, 100, 8), "pv8", 6, 12), "index")
    truth = shard.search_index(index, q, 5, 100).select("qid", "rank", "id", "score")
    search, parts = shard.search_index, []
    monkeypatch.setattr(shard, "search_index", lambda *args, **more: parts.append(more.get("parts", 1)) or search(*args, **more))
    tried = planner.choose_window(index, q, truth, 0.9, 5).collect()
    assert min(parts) == min(3, spark.sparkContext.defaultParallelism) and sum(r["chosen"] for r in tried) == 1
    alone, shared = (sorted(map(tuple, search(index, q, 5, 10, parts=n).collect())) for n in (1, 3))
    assert len(alone) == 3500 and alone == shared
