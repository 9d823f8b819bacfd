import itertools
import random

from vecengine.llm import sharding


def _cells(plan):
    groups = {}
    for n, begin, end, s, m in plan:
        for g in range(begin, end):
            assert s not in groups.setdefault((n, g), {})
            groups[n, g][s] = m
    return groups


def _together(groups):
    return sum(m * m for cells in groups.values() for m in cells.values())


def _case(rng, most=30):
    sizes = {n: rng.randint(1, 3) for n in rng.sample(range(2, most), rng.randint(1, 6))}
    linked, shards = sum(n * c for n, c in sizes.items()), rng.randint(2, 6)
    total = linked + rng.choice((0, 0, rng.randint(0, 10)))
    return sizes, [total // shards + (i < total % shards) for i in range(shards)]


def _valid(plan, sizes, quota):
    groups, load = _cells(plan), [0] * len(quota)
    assert sorted(groups) == sorted((n, g) for n, c in sizes.items() for g in range(c))
    for (n, _), cells in groups.items():
        assert sum(cells.values()) == n and min(cells.values()) > 0
        for s, m in cells.items():
            load[s] += m
    assert all(x <= q for x, q in zip(load, quota, strict=True))
    return groups


def test_full_shards_exchange_groups_until_none_is_cut():
    start = sharding._plan({4: 2, 3: 4}, [10, 10])
    assert any(m < n for n, *_, m in start)
    groups = _valid(sharding._propagate(start, [10, 10]), {4: 2, 3: 4}, [10, 10])
    assert all(len(cells) == 1 for cells in groups.values())


def test_rounds_never_raise_the_cut_and_keep_every_row(monkeypatch):
    rng, better = random.Random(7), 0
    for sums in (sharding.SUMS, 8):
        monkeypatch.setattr(sharding, "SUMS", sums)
        for _ in range(200):
            sizes, quota = _case(rng)
            start = sharding._plan(sizes, quota)
            before, after = (_together(_valid(plan, sizes, quota)) for plan in (start, sharding._propagate(start, quota)))
            assert after >= before
            better += after > before
    assert better > 100


def test_after_the_rounds_no_exchange_of_two_members_lowers_the_cut():
    rng = random.Random(11)
    for _ in range(60):
        sizes, quota = _case(rng, 12)
        groups = _cells(sharding._propagate(sharding._plan(sizes, quota), quota))
        now = _together(groups)
        for (g, x), (h, y) in itertools.permutations(groups.items(), 2):
            for b, a in itertools.permutations(x, 2):
                if a in y:
                    d = min(x[b], y[a])
                    new = {**groups, g: {**x, b: x[b] - d, a: x[a] + d}, h: {**y, a: y[a] - d, b: y.get(b, 0) + d}}
                    assert _together(new) <= now


def test_members_dealt_over_all_shards_come_together():
    # Each group starts with one member in each shard.
    start = [(4, g, g + 1, s, 1) for g in range(4) for s in range(4)]
    groups = _valid(sharding._propagate(start, [4] * 4), {4: 4}, [4] * 4)
    assert all(len(cells) == 1 for cells in groups.values())
    moved = _valid(sharding._propagate([(4, 0, 1, 0, 2), (4, 0, 1, 1, 2)], [4, 4]), {4: 1}, [4, 4])
    assert len(moved[4, 0]) == 1


def test_copies_of_a_text_are_not_cut_where_an_exchange_avoids_it(spark):
    sizes = [4, 4, 3, 3, 3, 3]
    rows = [(10 * g + i, f"text {g}") for g, n in enumerate(sizes) for i in range(n)]
    got = sharding.balanced_shards(spark.createDataFrame(rows, "doc_id long, text string"), 2).persist()
    assert sorted(r["count"] for r in got.groupBy("shard").count().collect()) == [10, 10]
    assert tuple(sharding.cut_edges(got).first()) == (24, 0)
    assert sorted(r["doc_id"] for r in got.collect()) == sorted(i for i, _ in rows)
