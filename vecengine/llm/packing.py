"""Best-fit packing into bins of several permitted sequence lengths."""

from __future__ import annotations

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecengine.llm.common import small_batches, staged

CAPACITIES = (512, 1024, 2048, 4096, 8192)
#: Cost of a bin of c positions: BIN_COST + c + c * c / SPAN. The square is attention's share, so a long
#: bin pays only if it wastes less than short ones would.
BIN_COST, SPAN = 16, 65_536
#: A bin with a larger share of empty positions is packed again with those of other tasks, so many pieces at a time.
LOOSE, GROUP = 0.05, 50_000


def cost(capacity: int) -> float:
    return BIN_COST + capacity + capacity * capacity / SPAN


def _fill(lengths: list[int], order: list[int], sizes: list[int], floor: int) -> list[list[int]]:
    """Best fit, longest first: bins of places; a new bin gets the least permitted size that is ``floor`` at least and holds the piece."""
    rooms: dict[int, list[int]] = {}
    mask = 0  # bit r: some open bin has room r
    bins: list[list[int]] = []
    for i in order:
        n = lengths[i]
        fits = mask >> n
        if fits:
            r = n + (fits & -fits).bit_length() - 1
            b = rooms[r].pop()
            if not rooms[r]:
                mask &= ~(1 << r)
        else:
            r = next(c for c in sizes if c >= n and c >= floor)
            b = len(bins)
            bins.append([])
        bins[b].append(i)
        r -= n
        if r > 0:
            rooms.setdefault(r, []).append(b)
            mask |= 1 << r
    return bins


def _shrunk(used: int, sizes: list[int]) -> int:
    return next(c for c in sizes if c >= used)


def pack(lengths: list[int], capacities=CAPACITIES) -> list[tuple[int, int, int]]:
    """(bin, capacity, offset) of each length from 1 on; none may exceed the largest capacity.

    The sizes are chosen together: every permitted length is tried as the least
    that a new bin may have, each trial is best fit with the longest first (ties
    by place), and each bin shrinks to the smallest permitted length that holds
    its contents. The cheapest trial counts; what lies in its loosely filled
    bins is then tried again by itself, as long as that lowers the cost.
    """
    sizes = sorted(set(capacities))
    price = lambda bins: sum(cost(_shrunk(sum(lengths[i] for i in b), sizes)) for b in bins)

    def best(places: list[int]) -> list[list[int]]:
        order = sorted(places, key=lambda k: (-lengths[k], k))
        return min((_fill(lengths, order, sizes, s) for s in sizes), key=price)

    left, done = list(range(len(lengths))), []
    now = best(left)
    while True:
        used = [sum(lengths[i] for i in b) for b in now]
        loose = [b for b, u in zip(now, used, strict=True) if u < (1 - LOOSE) * _shrunk(u, sizes)]
        if len(loose) < 2 or len(loose) == len(now):
            break
        again = best([i for b in loose for i in b])
        if price(again) >= price(loose) - 1e-9:
            break
        done += [b for b, u in zip(now, used, strict=True) if u >= (1 - LOOSE) * _shrunk(u, sizes)]
        now = again
    out: list[tuple[int, int, int]] = [(0, 0, 0)] * len(lengths)
    for b, places in enumerate([*done, *now]):
        size, at = _shrunk(sum(lengths[i] for i in places), sizes), 0
        for i in places:
            out[i] = (b, size, at)
            at += lengths[i]
    return out


def best_fit(docs: DataFrame, capacities=CAPACITIES, id_col: str = "doc_id", text_col: str = "text", length_col: str | None = None, keep: tuple[str, ...] = ()) -> DataFrame:
    """Pack whole documents: (id, *keep, piece, start, length, bin, capacity, offset).

    A document's length is ``length_col`` or, without one, its words plus one
    for the mark at its end; null texts and lengths below 1 have length 1. A
    document longer than the largest capacity is cut into pieces of that
    capacity, and the rest; nothing is left out. Each task packs its own rows
    without a shuffle; then the pieces of all bins that stayed loose (LOOSE) are
    dealt to groups of about GROUP and packed again, so that tasks of few rows
    cost no bins of their own. ``bin`` is unique: the number of the task or
    group times 2^32 plus a count, and 2^61 more for the second packing. Equal
    lengths go by the row's values as text, then by piece. An empty table gives
    an empty result; repeated rows are pieces of their own.
    """
    small_batches(docs.sparkSession)
    sizes, largest = tuple(sorted(set(capacities))), max(capacities)
    what = F.col(length_col).cast("long") if length_col else F.col(text_col).cast("string")
    slim = docs.select(F.col(id_col), *keep, what.alias("__what"))
    width = len(slim.columns) - 1

    def run(batches):
        rows, pieces, schema = [], [], None
        for batch in batches:
            schema = batch.schema
            for values in zip(*(batch.column(i).to_pylist() for i in range(width)), (_length(x.as_py()) for x in batch.column(width)), strict=True):
                rows.append(values[:-1])
                pieces += [(len(rows) - 1, k, start, min(largest, values[-1] - start)) for k, start in enumerate(range(0, values[-1], largest))]
        if schema is not None:
            yield from _packed(rows, pieces, [(f.name, f.type) for f in schema][:-1], sizes, TaskContext.get().partitionId() << 32)

    kinds = ", ".join(f"`{n}` {t}" for n, t in slim.dtypes[:-1])
    schema = f"{kinds}, piece long, start long, length long, bin long, capacity long, offset long"
    first = staged(slim.mapInArrow(run, f"{schema}, __used long"), "packed")
    loose = F.col("__used") < (1 - LOOSE) * F.col("capacity")
    groups = max(1, -(-first.where(loose).count() // GROUP))

    def again(t: pa.Table) -> pa.Table:
        rows = list(zip(*(t.column(i).to_pylist() for i in range(width)), strict=True))
        pieces = list(zip(range(len(rows)), *(t.column(c).to_pylist() for c in ("piece", "start", "length")), strict=True))
        group = t.column("__group")[0].as_py()
        return pa.Table.from_batches(_packed(rows, pieces, [(f.name, f.type) for f in t.schema][:width], sizes, (1 << 61) + (group << 32), used=False))

    rest = first.where(loose).withColumn("__group", F.pmod(F.xxhash64("bin"), F.lit(groups)).cast("long")).drop("__used")
    return first.where(~loose).drop("__used").union(rest.groupBy("__group").applyInArrow(again, schema))


def _packed(rows: list[tuple], pieces: list[tuple[int, int, int, int]], columns, sizes, number: int, used: bool = True):
    """Batches of packed pieces (row, piece, start, length), bins numbered from ``number`` on."""
    order = sorted(pieces, key=lambda p: (tuple((x is None, str(x)) for x in rows[p[0]]), p[1:]))
    packed = pack([p[3] for p in order], sizes)
    full: dict[int, int] = {}
    for p, b in zip(order, packed, strict=True):
        full[b[0]] = full.get(b[0], 0) + p[3]
    for at in range(0, len(order), 10_000):
        part = list(zip(order[at : at + 10_000], packed[at : at + 10_000], strict=True))
        cols = [pa.array([rows[p[0]][c] for p, _ in part], kind) for c, (_, kind) in enumerate(columns)]
        made = [[p[1] for p, _ in part], [p[2] for p, _ in part], [p[3] for p, _ in part], [number + b[0] for _, b in part], [b[1] for _, b in part], [b[2] for _, b in part]]
        names = ["piece", "start", "length", "bin", "capacity", "offset"]
        if used:
            made.append([full[b[0]] for _, b in part])
            names.append("__used")
        yield pa.RecordBatch.from_arrays([*cols, *(pa.array(m, pa.int64()) for m in made)], [*(n for n, _ in columns), *names])


def _length(x) -> int:
    if isinstance(x, str):
        return len(x.split()) + 1
    return max(1, x or 1)


def report(packed: DataFrame) -> DataFrame:
    """Per capacity: bins, positions used, and the share filled."""
    bins = packed.groupBy("bin", "capacity").agg(F.sum("length").alias("used"))
    return bins.groupBy("capacity").agg(F.count("*").alias("bins"), F.sum("used").alias("used"), (F.sum("used") / F.sum("capacity")).alias("filled"))
