"""Exact Jaccard self-join of documents' word n-grams by a token-group matrix.

Documents with equal sets form a class. Two sets that are similar enough differ
in so few shingles that, of a fixed partition of all shingles into parts,
several parts hold the same of both; classes meet in the buckets of such parts,
and one that meets others in fewer buckets than a link needs is left out.

Classes that met the same first class are partitioned into (bounded) groups. The
matrix holds, for every group, the union of its shingles and the members' sizes.
Links come from the matrix alone, in two rounds of queries: first every class
asks the groups of the first classes of its buckets; then, once linked classes
are connected, it asks the groups of others that it met and is not connected
with. The overlap with a group's union bounds the overlap with any member, and
only groups that pass the bound are opened and compared member by member.
"""

from __future__ import annotations

import math
from functools import lru_cache

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from vecengine.llm.common import components, discard, small_batches, staged

#: Documents sampled to find shingles so common that they are left out of the
#: parts, texts of the sample that make one common, and the list's bound. They
#: steer the work only: no result depends on them.
SAMPLE, COMMON, COMMON_LIST = 4_000, 4, 200_000
#: Members of a group of the matrix.
GROUP = 32
#: Rows of ids up to which they are broadcast (about 64 bytes each in a hashed relation); beyond, texts are shuffled to them.
BROADCAST_ROWS = 4_000_000
_MEMO = 60_000
_RARE, _ALL = (0, 1), (2, 3, 4)  # attempts: first over uncommon shingles, then over all
#: Equal parts that a link needs, by the code in a part's low byte: four bits tell
#: the lane (attempt and parity of the pair's class), four the place in this list.
NEED = (1, 2, 3, 4, 6, 8, 12, 16, 24, 32, 48, 64, 96, 128, 192, 256)
_LANE, _CODE = "part & 15", "shiftrightunsigned(part, 4) & 15"


class _Words(dict):
    def __missing__(self, word: bytes) -> int:
        if len(self) >= _MEMO:
            self.clear()
        h = self[word] = xxhash.xxh3_64_intdigest(word)
        return h


def _mix(x: np.ndarray, salt: int) -> np.ndarray:
    """A bijective scramble of 64-bit numbers."""
    x = x ^ np.uint64(salt * 0x9E3779B97F4A7C15 & 0xFFFFFFFFFFFFFFFF)
    x = (x ^ (x >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
    x = (x ^ (x >> np.uint64(29))) * np.uint64(0xD6E8FEB86659FD93)
    return x ^ (x >> np.uint64(32))


def shingles(text: str | None, n: int, words: dict) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the n-word shingles; A-Z are lower-cased."""
    parts = (text or "").encode("utf-8", "replace").lower().split()
    if not parts:
        return np.empty(0, np.uint64)
    h = np.fromiter(map(words.__getitem__, parts), np.uint64, len(parts))
    width = min(n, len(h))
    out = np.full(len(h) - width + 1, width, np.uint64)
    for k in range(width):
        out = _mix(out, k + 1) + h[k : len(h) - width + 1 + k]
    return np.unique(_mix(out, 99))


def _marked(hashes: np.ndarray, pair: int, attempt: int, code: int) -> np.ndarray:
    return hashes & np.uint64(0xFFFFFFFFFFFFFF00) | np.uint64(code << 4 | (pair & 1) << 3 | attempt)


class Parts:
    """Part signatures for a threshold num/den."""

    def __init__(self, num: int, den: int, common: np.ndarray):
        self.num, self.den, self.common = num, den, common

    @lru_cache(maxsize=None)  # noqa: B019  one instance a worker
    def limits(self, j: int) -> tuple[int, int]:
        """Smallest size of class j, and smallest of the next: a partner is in the same class or next to it."""
        if j < 0:
            return 0, 1
        low = self.limits(j - 1)[1]
        return low, low * self.den // self.num + 1

    @lru_cache(maxsize=None)  # noqa: B019
    def of(self, size: int) -> int:
        j = 0
        while self.limits(j)[1] <= size:
            j += 1
        return j

    @lru_cache(maxsize=None)  # noqa: B019
    def shape(self, j: int) -> tuple[int, int, int]:
        """Parts, empty parts allowed, and the code of the equal parts needed, where the larger set of a pair is of class j.

        Sets of sizes a and b that link differ in at most
        (a + b)(den - num)/(den + num) shingles, so of that many parts and
        k + e more, k + e are equal, of which k are not empty if at most e are.
        """
        most = self.limits(j)[1] - 1
        differ = 2 * most * (self.den - self.num) // (self.den + self.num)
        least = max(1, self.limits(j - 1)[0])
        e, code = 0, max(i for i, k in enumerate(NEED) if k <= 1 + differ // 6)
        if differ > 1:
            for _ in range(30):
                m = differ + NEED[code] + e
                empty = m * math.exp(-least / m)
                e = max(1, math.ceil(empty + 1.5 * math.sqrt(empty)))
        return (differ + NEED[code] + e, e, code) if differ else (0, 0, 0)

    def signatures(self, s: np.ndarray) -> np.ndarray:
        j, out = self.of(len(s)), []
        rare = s
        if len(self.common):
            at = np.searchsorted(self.common, s)
            at[at == len(self.common)] = 0
            rare = s[self.common[at] != s]
        for pair in (j, j + 1):
            parts, e, code = self.shape(pair)
            if not parts:
                continue
            for attempt in (*_RARE, *_ALL):
                own = rare if attempt in _RARE else s
                scrambled = _mix(own, 1000 + attempt)
                # A multiply-shift of the high half deals shingles to parts.
                place = ((scrambled >> np.uint64(32)) * np.uint64(parts) >> np.uint64(32)).astype(np.int64)
                order = np.argsort(place, kind="stable")
                place = place[order]
                starts = np.flatnonzero(np.concatenate(([True], place[1:] != place[:-1]))) if len(place) else place
                if len(starts):
                    sums = np.add.reduceat(_mix(scrambled[order], 7), starts)
                    out.append(_marked(_mix(sums ^ _mix(place[starts].astype(np.uint64), pair * 16 + attempt), 5), pair, attempt, code))
                if parts - len(starts) <= e:
                    break
            else:
                out.append(_marked(_mix(np.array([pair], np.uint64), 31), pair, 7, 0))
        return np.concatenate(out) if out else np.empty(0, np.uint64)


def _longs(arrays: list) -> pa.Array:
    """Lists of 64-bit numbers."""
    offsets = np.concatenate(([0], np.cumsum([len(a) for a in arrays]))).astype(np.int32)
    return pa.ListArray.from_arrays(pa.array(offsets), pa.array(np.concatenate([np.empty(0, np.uint64), *arrays]).view(np.int64)))


def _key(sig: bytes) -> int:
    """What buckets know a class by: the first half of its signature."""
    return int.from_bytes(sig[:8], "little", signed=True)


def _sets(n: int):
    def run(batches):
        words = _Words()
        for batch in batches:
            for at in range(0, batch.num_rows, 100):
                part = batch.slice(at, 100)
                sets = [shingles(t.as_py(), n, words) for t in part.column(1)]
                sigs = [xxhash.xxh3_128_digest(s.tobytes()) for s in sets]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(sigs, pa.binary()), _longs(sets)], ["doc_id", "sig", "s"])

    return run


def _described(n: int):
    def run(batches):
        words = _Words()
        for batch in batches:
            sizes, sigs = [], []
            for t in batch.column(1):
                s = shingles(t.as_py(), n, words)
                sizes.append(len(s))
                sigs.append(xxhash.xxh3_128_digest(s.tobytes()))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(sizes, pa.int64()), pa.array(sigs, pa.binary()), pa.array(list(map(_key, sigs)), pa.int64())], ["doc_id", "n", "sig", "key"])

    return run


def _parted(n: int, num: int, den: int, common: np.ndarray):
    """(key, part): the parts of each class, once a task, so that copies move at most one a task."""
    def run(batches):
        words, parts, known = _Words(), Parts(num, den, common), set()
        for batch in batches:
            for at in range(0, batch.num_rows, 100):
                keys, found = [], []
                for t in batch.column(0).slice(at, 100):
                    s = shingles(t.as_py(), n, words)
                    key = _key(xxhash.xxh3_128_digest(s.tobytes()))
                    if len(s) and key not in known:
                        known.add(key)
                        keys.append(key)
                        found.append(parts.signatures(s))
                sizes = np.array([len(f) for f in found], np.int64)
                flat = np.concatenate([np.empty(0, np.uint64), *found]).view(np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(np.repeat(np.array(keys, np.int64), sizes), pa.int64()), pa.array(flat)], ["key", "part"])

    return run


def jaccard_components(docs: DataFrame, n: int = 5, num: int = 80, den: int = 100, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_shingles, component_id), one row per input row.

    Documents link when den * intersection >= num * union of their shingle
    sets. component_id is the smallest id reachable. Texts without words, and
    null texts, have empty sets and link with nothing; null ids take no part
    (their component is null). Rows that repeat an id with other texts join
    what each of their texts links. An empty table gives an empty result.
    """
    small_batches(docs.sparkSession)
    slim = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    common = _common(slim, n)
    rows = staged(slim.mapInArrow(_described(n), "doc_id long, n long, sig binary, key long"), "join-rows")
    live = rows.where("n > 0 and doc_id is not null")
    classes = staged(live.groupBy("sig").agg(F.min("doc_id").alias("rep"), F.first("key").alias("key")), "join-classes")
    # The texts are read again, so that no parts of copies are kept meanwhile.
    parts = slim.where("doc_id is not null").select("text").mapInArrow(_parted(n, num, den, common), "key long, part long")
    bucket, lane = Window.partitionBy("part"), Window.partitionBy("key", F.expr(_LANE))

    def meeting(rows: DataFrame) -> DataFrame:
        rows = rows.withColumn("lead", F.min("key").over(bucket)).withColumn("last", F.max("key").over(bucket))
        return rows.where("lead <> last").select("part", "key", "lead")

    # A class comes once from each task that saw it.
    any_met = staged(meeting(parts).select("part", "key").distinct(), "join-any-met")
    enough = any_met.withColumn("c", F.count("*").over(lane)).where(F.col("c") >= _need()).select("part", "key")
    keyed = staged(meeting(enough), "join-keyed")
    discard(any_met)
    needed = staged(classes.select("key", "rep").join(keyed.select("key").distinct(), "key", "left_semi"), "join-needed")
    named = needed.select(F.col("key").alias("lead"), F.col("rep").alias("lead_rep"))
    met = staged(keyed.join(needed, "key").join(named, "lead").select("part", "rep", F.col("lead_rep").alias("lead")), "join-met")
    discard(keyed)
    reps = needed.select("rep").distinct()
    asked = F.broadcast(reps) if reps.count() <= BROADCAST_ROWS else reps
    sets = slim.join(asked, slim.doc_id == asked["rep"], "left_semi").mapInArrow(_sets(n), "doc_id long, sig binary, s array<long>")
    sets = staged(sets.dropDuplicates(["doc_id", "sig"]).select(F.col("doc_id").alias("rep"), "s", F.size("s").cast("long").alias("n")), "join-sets")
    edges = _first_links(met, sets, num, den)
    comp = components(edges)
    more = _across(met, comp, sets, num, den)
    discard(met, needed, sets)
    # Rows that share an id but not a text make their classes one.
    repeated = live.join(classes.select("sig", "rep"), "sig").select(F.col("doc_id").alias("a"), F.col("rep").alias("b"))
    twice = live.groupBy("doc_id").agg(F.min("sig").alias("x"), F.max("sig").alias("y")).where("x <> y").select(F.col("doc_id").alias("a"))
    if twice.limit(1).count():
        more = more.union(repeated.join(twice, "a"))
    more = staged(more, "join-more")
    if more.limit(1).count():
        comp = components(edges.union(more))
    named = staged(classes.select("sig", "rep").join(comp, classes.rep == comp.id, "left").select("sig", F.coalesce("comp", "rep").alias("comp")), "join-shown")
    shown = rows.drop("key").join(named, "sig", "left")
    alone = (F.col("n") == 0) | F.col("doc_id").isNull()
    return shown.select("doc_id", F.col("n").alias("n_shingles"), F.when(alone, F.col("doc_id")).otherwise(F.col("comp")).alias("component_id"))


def _common(slim: DataFrame, n: int) -> np.ndarray:
    """Shingles that many different texts of a sample hold; at most COMMON_LIST."""
    total = slim.count()
    share = min(1.0, SAMPLE / max(total, 1))
    sample = slim.where(F.pmod(F.xxhash64("doc_id", F.lit(17)), F.lit(1_000_000)) < int(share * 1_000_000))
    sets = sample.mapInArrow(_sets(n), "doc_id long, sig binary, s array<long>").dropDuplicates(["sig"])
    least = max(COMMON, math.ceil(share * total / 1000)) if share < 1 else max(COMMON, total // 200)
    top = sets.select(F.explode("s").alias("t")).groupBy("t").agg(F.count("*").alias("c")).where(F.col("c") >= least)
    found = top.orderBy(F.desc("c"), "t").limit(COMMON_LIST).select("t").toPandas()["t"]
    return np.sort(found.to_numpy(np.int64).view(np.uint64))


def _need():
    """Equal parts that a link needs, from the code in a part."""
    return F.element_at(F.array(*map(F.lit, NEED)), F.expr(_CODE).cast("int") + 1)


def _often(batches):
    """Groups that a query met in as many parts as a link needs; a link's parts are all of one lane."""
    for batch in batches:
        reps, comps, kept = [], [], [np.empty(0, np.int64)]
        for rep, comp, need, groups in zip(*(batch.column(i) for i in range(4)), strict=True):
            ids, times = np.unique(groups.values.to_numpy(zero_copy_only=False), return_counts=True)
            ids = ids[times >= need.as_py()]
            reps.append(np.full(len(ids), rep.as_py()))
            comps.append(np.full(len(ids), comp.as_py()))
            kept.append(ids)
        flat = [np.concatenate([np.empty(0, np.int64), *x]).astype(np.int64) for x in (reps, comps, kept)]
        yield pa.RecordBatch.from_arrays([pa.array(x) for x in flat], ["rep", "comp", "group"])


def _chunks(members: DataFrame, pool: list[str]) -> DataFrame:
    """``members`` with ``group``: the rows of each ``pool`` dealt to groups of about GROUP."""
    counts = members.groupBy(*pool).agg(F.count("*").alias("all"))
    chunk = F.pmod(F.xxhash64("rep"), F.ceil(F.col("all") / GROUP)).cast("long")
    return members.join(counts, pool).withColumn("group", F.xxhash64(*pool, chunk)).drop("all")


def _matrix(placed: DataFrame, sets: DataFrame) -> DataFrame:
    """The token-group matrix of ``placed(rep, comp, group)``, a row a group: its union of shingles, the least and the largest member, and the members behind them."""
    member = F.struct("rep", "comp", "n", "s")
    rows = placed.join(sets, "rep").groupBy("group").agg(F.collect_list(member).alias("members"), F.min("n").alias("low"), F.max("n").alias("high"))
    return staged(rows.withColumn("union", F.array_distinct(F.flatten("members.s"))), "join-matrix")


def _opened(asks: DataFrame, sets: DataFrame, matrix: DataFrame, num: int, den: int) -> DataFrame:
    """Rows of ``asks(rep, comp, group)`` whose group may hold a link: its union overlaps the query's set enough, and some size fits. ``links`` are the members that do link."""
    asked = asks.join(sets, "rep").join(matrix, "group")
    fits = (F.col("high") * den >= F.col("n") * num) & (F.col("low") * num <= F.col("n") * den)
    opened = asked.where(fits & (F.size(F.array_intersect("s", "union")) * F.lit(den) >= F.col("n") * num))

    def links(m):
        other = (m["rep"] != F.col("rep")) & (F.col("comp").isNull() | (m["comp"] > F.col("comp")))
        near = F.least(m["n"], F.col("n")) * den >= F.greatest(m["n"], F.col("n")) * num
        return other & near & (F.size(F.array_intersect(m["s"], F.col("s"))) * F.lit(den + num) >= (m["n"] + F.col("n")) * num)

    return opened.select("rep", F.transform(F.filter("members", links), lambda m: m["rep"]).alias("links"))


def _first_links(met: DataFrame, sets: DataFrame, num: int, den: int) -> DataFrame:
    """Links (a, b) of each class into the groups of the first classes of its buckets: one for each group that it links with, which is enough to connect the two."""
    members = met.groupBy("rep").agg(F.min("lead").alias("pool")).withColumn("comp", F.lit(None).cast("long"))
    placed = staged(_chunks(members, ["pool"]).select("rep", "comp", "group"), "join-grouped")
    there = placed.select(F.col("rep").alias("lead"), "group")
    asks = met.where("rep <> lead").select("rep", "lead").distinct().join(there, "lead").select("rep", F.lit(None).cast("long").alias("comp"), "group").distinct()
    matrix = _matrix(placed, sets)
    found = _opened(asks, sets, matrix, num, den).where(F.size("links") > 0).select(F.col("rep").alias("a"), F.array_min("links").alias("b"))
    edges = staged(found, "join-edges")
    discard(placed, matrix)
    return edges


def _across(met: DataFrame, comp: DataFrame, sets: DataFrame, num: int, den: int) -> DataFrame:
    """Links between classes that met but are not connected yet.

    Groups are bounded pieces of what is connected, or, of the rest, of classes
    that met the same first class. What a query meets stays one row a group
    until it links.
    """
    lead = comp.select(F.col("id").alias("lead"), F.col("comp").alias("lead_comp"))
    named = staged(
        met.join(comp, met.rep == comp.id, "left").select("part", "rep", "lead", F.coalesce("comp", "rep").alias("comp"))
        .join(lead, "lead", "left").select("part", "rep", "lead", "comp", F.coalesce("lead_comp", "lead").alias("lead_comp")),
        "join-named",
    )
    mixed = staged(named.where("comp <> lead_comp").select("part").distinct(), "join-mixed")
    seen = staged(named.join(mixed, "part").select("part", "rep", "comp", "lead"), "join-seen")
    members = seen.groupBy("rep", "comp").agg(F.min("lead").alias("lead"))
    sizes = members.groupBy("comp").agg(F.count("*").alias("size"))
    pooled = members.join(sizes, "comp").withColumn("pure", F.col("size") >= GROUP // 4).withColumn("pool", F.when(F.col("pure"), F.col("comp")).otherwise(F.col("lead")))
    pooled = staged(pooled.select("rep", "comp", "pool", "pure"), "join-pooled")
    placed = staged(_chunks(pooled, ["pool", "pure"]).select("rep", "comp", F.when(F.col("pure"), F.col("pool")).alias("own"), "group"), "join-placed")
    located = staged(seen.join(placed.drop("comp"), "rep").select("part", "rep", "comp", "own", "group"), "join-located")
    there = staged(located.groupBy("part").agg(F.collect_set(F.struct("own", "group")).alias("groups")), "join-there")
    # A group of members that are all connected with the query has nothing to tell it.
    others = F.transform(F.filter("groups", lambda g: g["own"].isNull() | (g["own"] != F.col("comp"))), lambda g: g["group"])
    asks = located.select("part", "rep", "comp").join(there, "part").select("part", "rep", "comp", others.alias("groups")).where(F.size("groups") > 0)
    asks = asks.groupBy("rep", "comp", F.expr(_LANE).alias("lane"), _need().alias("need")).agg(F.flatten(F.collect_list("groups")).alias("groups"))
    asks = asks.select("rep", "comp", "need", "groups").mapInArrow(_often, "rep long, comp long, group long").distinct()
    asks = staged(asks, "join-asks")
    matrix = _matrix(placed.join(asks.select("group").distinct(), "group", "left_semi"), sets)
    found = staged(_opened(asks, sets, matrix, num, den).select(F.col("rep").alias("a"), F.explode("links").alias("b")), "join-across")
    discard(named, mixed, seen, pooled, placed, located, there, asks, matrix)
    return found


def keep_one(docs: DataFrame, n: int = 5, num: int = 80, den: int = 100, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The documents, of each linked group only that of the smallest id.

    Of rows that repeat this id one stays. Texts without words and rows without
    an id all stay. Columns are those of ``docs``.
    """
    found = staged(jaccard_components(docs, n, num, den, id_col, text_col).where("n_shingles > 0 and doc_id is not null"), "join-found")
    gone = staged(found.where("component_id <> doc_id").select(F.col("doc_id").alias("__gone")).distinct(), "join-gone")
    if gone.count() <= BROADCAST_ROWS:
        gone = F.broadcast(gone)
    kept = docs.join(gone, F.col(id_col).cast("long") == gone["__gone"], "left_anti")
    twice = found.where("component_id = doc_id").groupBy("doc_id").agg(F.count("*").alias("c")).where("c > 1").select(F.col("doc_id").alias("__twice"))
    if not twice.limit(1).count():
        return kept
    twice = staged(twice, "join-twice")
    text = F.trim(F.translate(F.coalesce(F.col(text_col).cast("string"), F.lit("")), "\t\n\x0b\x0c\r", "     "))
    some = kept.withColumn("__words", text != "").join(twice, F.col(id_col).cast("long") == twice["__twice"], "left")
    again = F.col("__twice").isNotNull() & F.col("__words")
    return some.where(~again).unionByName(some.where(again).dropDuplicates(["__twice"])).drop("__twice", "__words")
