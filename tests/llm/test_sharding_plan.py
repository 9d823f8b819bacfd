import random

from vecengine.llm import sharding


def test_no_move_into_free_room_lowers_the_cut():
    rng = random.Random(4)
    for _ in range(300):
        sizes = {n: rng.randint(1, 3) for n in rng.sample(range(2, 30), rng.randint(1, 6))}
        linked, shards = sum(n * c for n, c in sizes.items()), rng.randint(2, 6)
        total = linked + rng.choice((0, 0, rng.randint(0, 40)))
        quota = [total // shards + (i < total % shards) for i in range(shards)]
        plan, groups, room = sharding._plan(sizes, quota), {}, list(quota)
        for n, begin, end, s, m in plan:
            for g in range(begin, end):
                groups.setdefault((n, g), {})[s] = m
                room[s] -= m
        assert min(room) >= 0 and all(sum(v.values()) == n for (n, _), v in groups.items())
        for cells in groups.values():
            for c, m in cells.items():
                for b, other in cells.items():
                    for d in range(1, min(room[c], other) + 1):
                        assert b == c or (other - d) ** 2 + (m + d) ** 2 <= other**2 + m**2


def test_every_stage_of_balanced_shards_feeds_the_result(spark, monkeypatch):
    names, write = [], sharding.staged
    monkeypatch.setattr(sharding, "staged", lambda df, name: names.append(name) or write(df, name))
    docs = spark.createDataFrame([(i, f"text {i % 7}" if i < 90 else f"own {i}") for i in range(100)], "doc_id long, text string")
    got = sharding.balanced_shards(docs, 6).groupBy("shard").count().collect()
    assert sorted(r["count"] for r in got) == [16, 16, 17, 17, 17, 17]
    assert len(names) == len(set(names)) and not {"shard-moves", "shard-taken"} & set(names)
