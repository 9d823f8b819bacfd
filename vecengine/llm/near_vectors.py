"""Near-duplicate vectors by randomly rotated binary codes with stored correction factors.

Every vector is stored as the signs of randomly rotated components, the
correction factor of that code (its product with the unit vector), and the
rotated components in four bits each. Bands of sign bits bring candidates
together. For each pair that meets, the code of one side and the four bits of
the other give an unbiased estimate of the inner product with a confidence
bound; vectors are fetched only for rows with a pair that the bound leaves in
doubt or above, and only such pairs are recomputed in double precision.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecengine.llm.common import components, small_batches, staged
from vecengine.llm.vector_rows import sound

#: Standard errors that an estimate may be off; chance that a pair at the threshold meets in no band.
SIGMAS, MISS = 4.0, 0.005
BLOCK = 1024
SEED = 20_240_607
#: Sign bits of a code at least (whole rotations), and the steps of the four-bit side.
CODE_BITS, STEPS = 256, 15


def rotations(d: int, count: int) -> np.ndarray:
    """``count`` random rotations of d dimensions, stacked: (count * d, d)."""
    rng = np.random.default_rng(SEED)
    return np.concatenate([np.linalg.qr(rng.standard_normal((d, d)))[0].T for _ in range(count)])


def plan(n: int, threshold: float) -> tuple[int, int]:
    """Bits of a band, so that few vectors of n meet by chance, and bands for the recall."""
    bits = max(6, math.ceil(math.log2(max(n, 2))) + 2)
    same = (1 - math.acos(min(threshold, 1.0)) / math.pi) ** bits
    return bits, max(1, math.ceil(math.log(MISS) / math.log1p(-min(same, 1 - 1e-12))))


class Coder:
    """Codes and band keys of unit vectors of one length."""

    def __init__(self, d: int, bits: int, bands: int):
        self.d, self.turns = d, max(1, -(-CODE_BITS // d))
        self.turn = rotations(d, max(self.turns, -(-min(bits * bands, 16 * d) // d)))
        self.width = self.turns * d
        rng = np.random.default_rng(SEED + 1)
        self.picks = np.stack([rng.choice(len(self.turn), bits, replace=len(self.turn) < bits) for _ in range(bands)])
        self.weights = rng.integers(1, 1 << 62, bits, dtype=np.int64) | 1

    def of(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Band keys (n, bands), signs and the four bit planes of the components as words, and (factor, low, step) of each row."""
        y = x @ self.turn.T
        with np.errstate(over="ignore"):
            # The length is part of a key: vectors of two lengths never meet.
            keys = np.where((y > 0)[:, self.picks], self.weights, self.d).sum(axis=2).astype(np.int64) * 31 + self.d
        y = y[:, : self.width]
        factor = np.abs(y).sum(axis=1) / (self.turns * math.sqrt(self.d))
        low = y.min(axis=1)
        step = np.maximum(y.max(axis=1) - low, 1e-300) / STEPS
        fine = np.floor((y - low[:, None]) / step[:, None] + 0.5).astype(np.uint8)
        planes = np.concatenate([self._words(fine >> p & 1) for p in range(4)], axis=1)
        return keys, self._words(y > 0), planes, np.column_stack([factor, low, step])

    def _words(self, bits: np.ndarray) -> np.ndarray:
        """Bits as 64-bit words, filled up with zeros."""
        return np.packbits(np.pad(bits, ((0, 0), (0, -self.width % 64))), axis=1).view(np.uint64)

    def estimates(self, codes: np.ndarray, planes: np.ndarray, consts: np.ndarray):
        """A function (i, j) of places: upper confidence bounds of the inner products of their rows, by counting bits."""
        codes, planes = codes.view(np.uint64), planes.view(np.uint64).reshape(len(codes), 4, -1)
        factor, low, step = consts.T
        weight, scale = np.array([1.0, 2.0, 4.0, 8.0]), 1 / (self.turns * math.sqrt(self.d))
        ones = np.bitwise_count(codes).sum(axis=1, dtype=np.int64)
        fines = np.bitwise_count(planes).sum(axis=2, dtype=np.int64) @ weight
        # Each rotation is an estimate of its own; their mean errs by the root of their number less.
        error = SIGMAS * np.sqrt(np.maximum(1 - factor**2, 0)) / factor / math.sqrt(max(self.d - 1, 1) * self.turns)

        def upper(i, j):
            both = np.bitwise_count(codes[j][:, None, :] & planes[i]).sum(axis=2, dtype=np.int64) @ weight
            # Signs are 1 and -1: twice the components under a one, less all of them.
            product = step[i] * (2 * both - fines[i]) + low[i] * (2 * ones[j] - self.width)
            # Rounding to four bits errs by half a step at most, in either direction alike.
            return product * scale / factor[j] + error[j] + SIGMAS * step[i] / math.sqrt(12) * math.sqrt(self.width) * scale / factor[j]

        return upper


def _unit(column: pa.Array, d: int) -> np.ndarray:
    x = column.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(-1, d)
    # Scaling first keeps squares of tiny and huge components finite.
    x = x / np.abs(x).max(axis=1, keepdims=True)
    return x / np.linalg.norm(x, axis=1, keepdims=True)


_CODE = "d int, keys array<long>, code binary, fine binary, factor double, low double, step double"


def _coded(bits: int, bands: int):
    def run(batches):
        coders: dict[int, Coder] = {}
        for batch in batches:
            sizes = np.asarray(pc.list_value_length(batch.column(1)))
            for d in np.unique(sizes).tolist():
                coder = coders.get(d) or coders.setdefault(d, Coder(d, bits, bands))
                places = np.flatnonzero(sizes == d)
                for at in range(0, len(places), 512):
                    part = batch.take(pa.array(places[at : at + 512]))
                    keys, code, fine, consts = coder.of(_unit(part.column(1), d))
                    listed = pa.ListArray.from_arrays(np.arange(0, keys.size + 1, bands, dtype=np.int32), pa.array(keys.ravel()))
                    raw = [pa.array([c.tobytes() for c in x], pa.binary()) for x in (code, fine)]
                    cols = [part.column(0), pa.array(np.full(len(keys), d, np.int32)), listed, *raw, *(pa.array(c) for c in consts.T)]
                    yield pa.RecordBatch.from_arrays(cols, ["rep", *(f.split()[0] for f in _CODE.split(", "))])

    return run


_GROUP = ["band", "key", "b1", "b2"]


def _whole_groups(batches):
    """Tables that end with a group's last row; rows come sorted by group."""
    tail = None
    for batch in batches:
        if not batch.num_rows:
            continue
        whole = pa.Table.from_batches([batch] if tail is None else [tail, batch]).combine_chunks()
        names = [whole.column(c).to_numpy() for c in _GROUP]
        change = np.flatnonzero(np.any([x[1:] != x[:-1] for x in names], axis=0)) + 1
        cut = int(change[-1]) if len(change) else 0
        if cut:
            yield whole.slice(0, cut).combine_chunks()
        tail = whole.slice(cut).combine_chunks().to_batches()[0]
    if tail is not None:
        yield pa.Table.from_batches([tail])


class _Pairs:
    """Pairs of rows of a table of whole groups, and the bounds of their products."""

    def __init__(self, t: pa.Table, coders: dict, bits: int, bands: int):
        names = [t.column(c).to_numpy() for c in _GROUP]
        self.run = np.concatenate(([0], np.cumsum(np.any([x[1:] != x[:-1] for x in names], axis=0))))
        self.cross, self.blk, self.n = names[2] != names[3], t.column("blk").to_numpy(), t.num_rows
        d = t.column("d").to_numpy()
        # A group's rows are of one length, for it is part of the key.
        self.bounds, self.place, self.length = {}, np.zeros(self.n, np.int64), d
        for one in np.unique(d).tolist():
            coder = coders.get(one) or coders.setdefault(one, Coder(one, bits, bands))
            at = np.flatnonzero(d == one)
            self.place[at] = np.arange(len(at))
            raw = [np.frombuffer(b"".join(t.column(c).take(pa.array(at)).to_pylist()), np.uint8).reshape(len(at), -1) for c in ("code", "fine")]
            consts = np.column_stack([t.column(c).to_numpy()[at] for c in ("factor", "low", "step")])
            self.bounds[one] = coder.estimates(*raw, consts)

    def doubtful(self, threshold: float):
        """Blocks (i, j) of places whose product may reach the threshold."""
        at, lag = np.arange(self.n), 0
        while len(at):
            lag += 1
            at = at[at + lag < self.n]
            at = at[self.run[at] == self.run[at + lag]]
            for lo in range(0, len(at), 20_000):
                i = at[lo : lo + 20_000]
                i = i[~self.cross[i] | (self.blk[i] != self.blk[i + lag])]
                keep = np.zeros(len(i), bool)
                for d, upper in self.bounds.items():
                    own = np.flatnonzero(self.length[i] == d)
                    keep[own] = upper(self.place[i[own]], self.place[i[own] + lag]) >= threshold
                if keep.any():
                    yield i[keep], i[keep] + lag


def near_vectors(db: DataFrame, threshold: float = 0.95, id_col: str = "vec_id", vec_col: str = "embedding") -> DataFrame:
    """(vec_id, n_links, component_id, kept) of every row.

    Vectors link when they are of one length and their cosine, recomputed in
    double precision, is at least ``threshold`` (at most 1). Equal vectors are
    one class that stands for all its rows. Null, empty, zero, or non-finite
    vectors link with nothing, nor do rows with a null id. A link is found with
    probability 1 - MISS at the threshold and more above it. An empty table
    gives an empty result. What a bucket of many unlike classes costs is the
    product of its blocks; only bounded blocks meet, and pairs never leave them.
    """
    small_batches(db.sparkSession)
    rows = db.select(F.col(id_col).cast("long").alias("vec_id"), F.col(vec_col).cast("array<double>").alias("vec"))
    good = sound("vec") & F.exists("vec", lambda x: x != 0)
    rows = staged(rows.select("vec_id", "vec", F.when(good, F.xxhash64("vec")).alias("h1"), F.when(good, F.xxhash64(F.lit(1), F.reverse("vec"))).alias("h2")), "near-rows")
    classes = staged(rows.where("h1 is not null and vec_id is not null").groupBy("h1", "h2").agg(F.min("vec_id").alias("id"), F.count("*").alias("m"), F.first("vec").alias("vec")).withColumn("rep", F.col("h1")), "near-classes")
    bits, bands = plan(classes.count(), threshold)
    codes = staged(classes.select("rep", "vec").mapInArrow(_coded(bits, bands), f"rep long, {_CODE}"), "near-codes")
    banded = codes.select("rep", F.posexplode("keys").alias("band", "key"))
    full = staged(banded.groupBy("band", "key").agg(F.count("*").alias("c")).where("c > 1"), "near-full")
    met = banded.join(full, ["band", "key"])
    # Large buckets go block by block: each pair of blocks is a group of its own.
    met = met.withColumn("blocks", F.ceil(F.col("c") / BLOCK).cast("int")).withColumn("blk", F.pmod(F.xxhash64("rep"), F.col("blocks")).cast("int"))
    met = met.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    met = staged(met.select("band", "key", F.least("blk", "other").alias("b1"), F.greatest("blk", "other").alias("b2"), "blk", "rep"), "near-met")

    def grouped(df: DataFrame) -> DataFrame:
        return df.repartition(*_GROUP).sortWithinPartitions(*_GROUP, "rep")

    def doubts(batches):
        coders: dict[int, Coder] = {}
        for t in _whole_groups(batches):
            flag = np.zeros(t.num_rows, bool)
            for i, j in _Pairs(t, coders, bits, bands).doubtful(threshold):
                flag[i] = flag[j] = True
            kept = t.select([*_GROUP, "blk", "rep"]).filter(pa.array(flag))
            yield from kept.to_batches()

    kinds = "band int, key long, b1 int, b2 int, blk int, rep long"
    coded = grouped(met.join(codes.drop("keys"), "rep").select(*_GROUP, "blk", "rep", "d", "code", "fine", "factor", "low", "step"))
    doubtful = staged(coded.mapInArrow(doubts, kinds), "near-doubtful")

    def compare(batches):
        coders: dict[int, Coder] = {}
        for t in _whole_groups(batches):
            yield _links(t, _Pairs(t, coders, bits, bands), threshold, bands)

    loaded = grouped(doubtful.join(codes, "rep").join(classes.select("rep", "vec", "m"), "rep").select(*_GROUP, "blk", "rep", "m", "vec", "keys", "d", "code", "fine", "factor", "low", "step"))
    found = staged(loaded.mapInArrow(compare, "a long, b long, links long"), "near-links")
    links = found.where("links > 0").groupBy(F.col("a").alias("rep")).agg(F.sum("links").alias("links"))
    comp = components(found.where("b is not null").select("a", "b")).withColumnRenamed("id", "rep")
    # Classes go by a hash of the vector, for an id may repeat with another vector; a component's name is its smallest id.
    named = classes.drop("vec").join(links, "rep", "left").join(comp, "rep", "left")
    least = classes.join(comp, "rep").groupBy("comp").agg(F.min("id").alias("least"))
    known = staged(
        named.join(least, "comp", "left")
        .select("h1", "h2", (F.col("m") - 1 + F.coalesce("links", F.lit(0))).alias("n_links"), F.coalesce("least", "id").alias("comp")),
        "near-known",
    )
    return rows.select("vec_id", "h1", "h2").join(known, ["h1", "h2"], "left").select(
        "vec_id", F.when(F.col("vec_id").isNotNull(), F.coalesce("n_links", F.lit(0))).otherwise(0).cast("long").alias("n_links"),
        F.when(F.col("vec_id").isNotNull(), F.coalesce("comp", "vec_id")).alias("component_id"),
        F.coalesce(F.coalesce("comp", "vec_id") == F.col("vec_id"), F.lit(True)).alias("kept"),
    )


def _links(t: pa.Table, pairs: _Pairs, threshold: float, bands: int) -> pa.RecordBatch:
    """Verified links of whole groups: sums of links per vector, and edges that connect what is linked."""
    rep, m, band = t.column("rep").to_numpy(), t.column("m").to_numpy(), t.column("band").to_numpy()
    keys = t.column("keys").combine_chunks().flatten().to_numpy().reshape(-1, bands)
    length, vec, unit, place = pairs.length, t.column("vec").combine_chunks(), {}, pairs.place
    for d in np.unique(length).tolist():
        unit[d] = _unit(vec.take(pa.array(np.flatnonzero(length == d))), d)
    links, head, edges = np.zeros(len(rep), np.int64), np.arange(len(rep)), []
    for i, j in pairs.doubtful(threshold):
        same = np.zeros(len(i))
        for d, x in unit.items():
            own = np.flatnonzero(length[i] == d)
            same[own] = np.einsum("ij,ij->i", x[place[i[own]]], x[place[j[own]]])
        i, j = i[same >= threshold], j[same >= threshold]
        # A pair counts in the first band where it meets.
        before = (keys[i] == keys[j]) & (np.arange(bands) < band[i][:, None])
        first = ~before.any(axis=1)
        i, j = i[first], j[first]
        np.add.at(links, i, m[j])
        np.add.at(links, j, m[i])
        # An edge is told unless both ends are known to hang on one head.
        x, y = head[i], head[j]
        fresh = x != y
        edges.append(np.column_stack((rep[i[fresh]], rep[j[fresh]])))
        np.minimum.at(head, np.maximum(x, y)[fresh], np.minimum(x, y)[fresh])
        while (head[head] != head).any():
            head = head[head]
    has = np.flatnonzero(links)
    ab = np.concatenate([np.empty((0, 2), np.int64), *edges])
    a, b = np.concatenate((rep[has], ab[:, 0])), np.concatenate((np.zeros(len(has), np.int64), ab[:, 1]))
    none = np.concatenate((np.ones(len(has), bool), np.zeros(len(ab), bool)))
    return pa.RecordBatch.from_arrays([pa.array(a), pa.array(b, mask=none), pa.array(np.concatenate((links[has], np.zeros(len(ab), np.int64))))], ["a", "b", "links"])
