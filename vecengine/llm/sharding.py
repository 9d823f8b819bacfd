"""Even shards that keep linked documents together: placed whole, then balanced label propagation with exchanges.

Documents with equal texts are linked. All state is counts of (group, shard),
so a group of any size is at most one row a shard; groups of one size are alike,
so the moves are worked out on counts of (size, shard). DataFrame functions only.
"""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from vecengine.llm.common import staged

#: Rows that one window partition ranks; more rows make more partitions.
RANKED = 8_192
#: Members that an exchange makes up from whole groups in every possible way; of more, the largest groups go first.
SUMS = 4_096


def numbered(df: DataFrame, part: list[str], order: list[str], total: str, name: str = "slot") -> DataFrame:
    """Gapless numbers from 0 within ``part``, without one task for a large part.

    Rows of a part are dealt by hash of ``order`` to buckets of about RANKED
    rows (``total``: SQL for the part's rows); each is ranked by itself and
    starts where the buckets before it end. Rows equal in ``order`` are alike.
    """
    deal = F.pmod(F.xxhash64(*order), F.ceil(F.expr(total) / F.lit(float(RANKED))).cast("long"))
    dealt = df.withColumn("__bucket", F.coalesce(deal, F.lit(0)))
    before = Window.partitionBy(*(part or [F.lit(0)])).orderBy("__bucket").rowsBetween(Window.unboundedPreceding, -1)
    starts = (
        dealt.groupBy(*part, "__bucket").agg(F.count("*").alias("__n"))
        .withColumn("__start", F.coalesce(F.sum("__n").over(before), F.lit(0))).drop("__n")
    )
    rank = F.row_number().over(Window.partitionBy(*part, "__bucket").orderBy(*order))
    ranked = dealt.withColumn("__rank", rank)
    return ranked.join(starts, [*part, "__bucket"]).withColumn(name, F.col("__start") + F.col("__rank") - 1).drop("__bucket", "__start", "__rank")


def _sized(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    text = F.col(text_col).cast("string")
    return docs.select(
        F.col(id_col).cast("long").alias("doc_id"),
        (F.coalesce(F.octet_length(text), F.lit(0)) + 1).cast("long").alias("size"),
        F.coalesce(F.crc32(text), F.lit(0)).cast("long").alias("text_crc32"),
        F.xxhash64(text).alias("__h"),
    )


def balanced_shards(docs: DataFrame, n_shards: int = 16, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Shards of equal row counts, equal texts together where that is possible.

    Returns (doc_id, size, text_crc32, law='rows', shard, slot, grown_shard
    null, n_copies), one row per input row; row counts of shards differ by one
    at most. Groups are placed first, the largest first; one is cut only if no
    shard has room for it when its turn comes, and then into the fewest pieces.
    In the rounds after that, members of cut groups move to where more of their
    group are, into free room or in exchange for other groups or members, as long
    as that lowers the cut. Documents without links fill up what is left. Null texts
    are linked with each other and with empty texts' size only if null; ids may
    be null or repeated. An empty table gives an empty result.
    """
    rows = staged(_sized(docs, id_col, text_col), "shard-rows")
    total = rows.count()
    key = ["__h", "text_crc32", "size"]
    groups = staged(rows.groupBy(*key).agg(F.count("*").alias("n")).where("n > 1"), "shard-groups")
    n_groups, n_linked = groups.agg(F.count("*"), F.coalesce(F.sum("n"), F.lit(0))).first()
    quota = [total // n_shards + (i < total % n_shards) for i in range(n_shards)]

    cells, load = None, [0] * n_shards
    if n_groups:
        # Whole groups, by the number of groups of each size.
        by_size = groups.groupBy("n").agg(F.count("*").alias("of_size"))
        sizes = {r["n"]: r["of_size"] for r in by_size.collect()}
        plan = F.from_json(F.lit(json.dumps([dict(zip(("n", "begin", "end", "shard", "m"), x, strict=True)) for x in _propagate(_plan(sizes, quota), quota)])), "array<struct<n:long,begin:long,end:long,shard:int,m:long>>")
        plan = docs.sparkSession.range(1).select(F.explode(plan).alias("p")).select("p.*").withColumnRenamed("n", "of")
        each = numbered(groups.join(F.broadcast(by_size), "n"), ["n"], key, "of_size", "g")
        here = (F.col("n") == F.col("of")) & (F.col("g") >= F.col("begin")) & (F.col("g") < F.col("end"))
        # Sizes differ, so there are at most about 16 sqrt(2 rows) rows to broadcast, and those of the cut groups.
        cells = staged(each.join(F.broadcast(plan), here).select(*key, "shard", "m"), "shard-cells")
        load = _loads(cells, n_shards)

    spare = [q - x for q, x in zip(quota, load, strict=True)]
    if n_groups:
        run = F.sum("m").over(Window.partitionBy(*key).orderBy("shard"))
        shares = staged(cells.withColumn("upto", run).groupBy(*key).agg(F.sum("m").alias("n_copies"), F.sort_array(F.collect_list(F.struct("upto", "shard"))).alias("cells")), "shard-shares")
        known = rows.join(shares, key, "left")
    else:
        known = rows.withColumn("n_copies", F.lit(None).cast("long")).withColumn("cells", F.lit(None).cast("array<struct<upto:long,shard:int>>"))
    known = staged(known, "shard-known")
    order = ["doc_id", *key]
    linked = numbered(known.where("cells is not null"), key, order, "n_copies", "__r")
    linked = linked.withColumn("shard", F.element_at(F.filter("cells", lambda c: c["upto"] > F.col("__r")), 1)["shard"])
    ends = [sum(spare[: i + 1]) for i in range(n_shards)]
    fill = F.array(*(F.struct(F.lit(e).cast("long").alias("upto"), F.lit(i).alias("shard")) for i, e in enumerate(ends)))
    single = numbered(known.where("cells is null"), [], order, str(max(1, total - n_linked)), "__r")
    single = single.withColumn("shard", F.element_at(F.filter(fill, lambda c: c["upto"] > F.col("__r")), 1)["shard"])
    cols = [*order, F.coalesce("n_copies", F.lit(1)).cast("long").alias("n_copies"), F.col("shard").cast("int").alias("shard")]
    placed = staged(linked.select(*cols).unionByName(single.select(*cols)), "shard-placed")
    slotted = numbered(placed, ["shard"], order, str(max(1, total // n_shards)))
    return slotted.select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", F.col("slot").cast("long").alias("slot"), F.lit(None).cast("int").alias("grown_shard"), "n_copies")


def _plan(sizes: dict[int, int], quota: list[int]) -> list[tuple[int, int, int, int, int]]:
    """(size, begin, end, shard, members): the groups begin..end-1 of a size have so many members there."""
    room, out = list(quota), []
    for n in sorted(sizes, reverse=True):
        at, count = 0, sizes[n]
        for s in sorted(range(len(room)), key=lambda s: (-room[s], s)):
            whole = min(count - at, room[s] // n)
            if whole:
                out.append((n, at, at + whole, s, n))
                room[s] -= whole * n
                at += whole
        # No shard has room for one more: fewer of them are left than there are shards.
        for g in range(at, count):
            left = n
            for s in sorted(range(len(room)), key=lambda s: (-room[s], s)):
                m = min(left, room[s])
                if m:
                    out.append((n, g, g + 1, s, m))
                    room[s] -= m
                    left -= m
    return out


def _propagate(plan: list[tuple[int, int, int, int, int]], quota: list[int]) -> list[tuple[int, int, int, int, int]]:
    """The plan after rounds of moves, each the one that lowers the cut most, until none does.

    Members of a cut group go from one of its shards to another, its goal. If the
    goal has no room for them, it sends back others: whole groups, for which
    whole groups of the other shard may come along so that the sums meet, or
    else members of one more group, if what that cuts is less than what is won.
    """
    room, whole, cut = list(quota), [{} for _ in quota], {}
    for n, begin, end, s, m in plan:
        room[s] -= m * (end - begin)
        if m == n:
            whole[s][n] = whole[s].get(n, 0) + end - begin
        else:
            for g in range(begin, end):
                cut.setdefault((n, g), {})[s] = m
    while True:
        moves = (_exchange(key, a, b, d, whole, cut, room) for key, cells in cut.items() for a in cells for b in cells if a != b for d in _amounts(key, a, cells[b], cut, room))
        move = max((m for m in moves if m and m[0] > 0), key=lambda m: m[0], default=None)
        if move is None:
            break
        _, key, a, b, d, give, back, split = move
        for source, target, groups in ((a, b, give), (b, a, back)):
            for n, k in groups.items():
                whole[source][n] -= k
                whole[target][n] = whole[target].get(n, 0) + k
        left = d + sum(n * k for n, k in back.items()) - sum(n * k for n, k in give.items())
        _shift(cut[key], b, a, d)
        if split:
            other, r = split
            left -= r
            if isinstance(other, int):
                whole[a][other] -= 1
                other = (other, 1 + max((g for _, g in cut), default=0))
                cut[other] = {a: other[0]}
            _shift(cut[other], a, b, r)
        room[a], room[b] = room[a] - left, room[b] + left
        for other in [k for k, cells in cut.items() if len(cells) == 1]:
            (s,) = cut.pop(other)
            whole[s][other[0]] = whole[s].get(other[0], 0) + 1
    out, at = [], {}
    pieces = [(n, s, k, [(s, n)]) for s, groups in enumerate(whole) for n, k in groups.items() if k]
    pieces += [(n, len(quota), 1, sorted(cells.items())) for (n, _), cells in sorted(cut.items())]
    for n, _, k, cells in sorted(pieces, key=lambda p: (-p[0], p[1])):
        begin = at.get(n, 0)
        at[n] = begin + k
        out += [(n, begin, begin + k, s, m) for s, m in cells]
    return out


def _shift(cells: dict[int, int], source: int, target: int, d: int) -> None:
    cells[target] = cells.get(target, 0) + d
    cells[source] -= d
    if not cells[source]:
        del cells[source]


def _amounts(key: tuple[int, int], a: int, p: int, cut: dict, room: list[int]) -> set[int]:
    """How many of a piece of p members may move to shard a: all, as many as fit, or as many as another cut group has there."""
    there = (cells[a] for other, cells in cut.items() if other != key and a in cells)
    return {min(p, m) for m in (p, room[a], *(m + room[a] for m in there))} - {0}


def _exchange(key: tuple[int, int], a: int, b: int, d: int, whole: list[dict], cut: dict, room: list[int]) -> tuple | None:
    """(gain, key, a, b, d, groups given to b, groups taken from b, (group or size that is split, members)) of d members moved from b to a.

    The gain is the fall of the cut, twice: the rise of the sum of squares of the counts of (group, shard).
    """
    cells = cut[key]
    gain = 2 * d * (cells[a] - cells[b] + d)
    if gain <= 0:
        # Whatever goes back could be moved by itself.
        return None
    mine, give, rest = dict(whole[a]), {}, d
    for n in sorted(mine, reverse=True):
        k = min(mine[n], max(0, rest - room[a]) // n) if rest - room[a] > SUMS else 0
        if k:
            give[n], rest = k, rest - k * n
            mine[n] -= k
    own, other = _sums(mine), _sums(whole[b])
    back = other[1][-1]
    while back:
        v = (back & -back).bit_length() - 1
        back &= back - 1
        low, high = max(0, rest + v - room[a]), min(SUMS, rest + v + room[b])
        fit = (own[1][-1] >> low) & ((1 << (high - low + 1)) - 1) if low <= high else 0
        if fit:
            more = _pick(*own, low + (fit & -fit).bit_length() - 1)
            return gain, key, a, b, d, {n: give.get(n, 0) + more.get(n, 0) for n in give | more}, _pick(*other, v), None
    # No whole groups meet the sum: the least loss by one that is split, with or without whole ones beside it.
    need, best = rest - room[a], None
    near = (own[1][-1] & ((1 << (need + 1)) - 1)).bit_length() - 1
    for total in {0, near}:
        r, more = need - total, _pick(*own, total)
        larger = [n for n, k in mine.items() if n > r and k > more.get(n, 0)]
        options = [(2 * r * (min(larger) - r), min(larger))] if larger else []
        options += [(2 * r * (c[a] - c.get(b, 0) - r), k) for k, c in cut.items() if k != key and c.get(a, 0) >= r]
        for loss, which in options:
            if best is None or gain - loss > best[0]:
                best = (gain - loss, key, a, b, d, {n: give.get(n, 0) + more.get(n, 0) for n in give | more}, {}, (which, r))
    return best


def _sums(groups: dict[int, int]) -> tuple[list[tuple[int, int]], list[int]]:
    """Sums up to SUMS that groups (size: number) can make, as bits, after each of the (size, number) that are taken or left."""
    items, reach = [], [1]
    for n in sorted(groups):
        left, chunk = min(groups[n], SUMS // n), 1
        while left:
            k = min(chunk, left)
            items.append((n, k))
            reach.append((reach[-1] | reach[-1] << n * k) & ((1 << (SUMS + 1)) - 1))
            left, chunk = left - k, 2 * chunk
    return items, reach


def _pick(items: list[tuple[int, int]], reach: list[int], total: int) -> dict[int, int]:
    """Groups (size: number) that make up a sum."""
    out = {}
    for (n, k), before in zip(reversed(items), reversed(reach[:-1]), strict=True):
        if not before >> total & 1:
            out[n], total = out.get(n, 0) + k, total - n * k
    return out


def cut_edges(sharded: DataFrame) -> DataFrame:
    """One row (edges, cut): pairs of equal texts, and those in two shards.

    Texts count as equal if checksum, size and number of copies are.
    """
    pairs = lambda n: F.col(n).cast("decimal(19,0)") * (F.col(n) - 1).cast("decimal(19,0)") / 2
    key = ["text_crc32", "size", "n_copies"]
    cells = sharded.where("n_copies > 1").groupBy(*key, "shard").agg(F.count("*").alias("m"))
    groups = cells.groupBy(*key).agg(F.sum("m").alias("n"), F.sum(pairs("m")).alias("inside"))
    sums = groups.agg(*(F.coalesce(F.sum(x), F.lit(0)).cast("decimal(38,0)").alias(n) for x, n in ((pairs("n"), "edges"), (pairs("n") - F.col("inside"), "cut"))))
    return sums


def _loads(cells: DataFrame, n_shards: int) -> list[int]:
    got = dict(cells.groupBy("shard").agg(F.sum("m")).collect())
    return [got.get(i, 0) for i in range(n_shards)]


def key_shards(docs: DataFrame, n_shards: int = 16, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The law 'key': the id's highest hash with a shard's number wins it.

    One more shard takes rows only into itself (grown_shard). Null ids count as
    one id. Narrow but for the slots.
    """
    def win(n: int):
        return F.array_max(F.transform(F.sequence(F.lit(0), F.lit(n - 1)), lambda s: F.struct(F.xxhash64(F.col("doc_id"), s).alias("h"), s.alias("s"))))["s"]

    rows = _sized(docs, id_col, text_col).withColumn("shard", win(n_shards).cast("int")).withColumn("grown_shard", win(n_shards + 1).cast("int"))
    rows = staged(rows, "shard-key")
    slotted = numbered(rows, ["shard"], ["doc_id", "__h", "text_crc32", "size"], str(max(1, rows.count() // n_shards)))
    return slotted.select("doc_id", "size", "text_crc32", F.lit("key").alias("law"), "shard", F.col("slot").cast("long").alias("slot"), "grown_shard")
