"""Shard-local graphs: built, searched and re-ranked within one task each.

A shard is one row of flat arrays: ids, codes (one or two levels, apart),
constants, and neighbour lists of fixed stride. Many queries move through the
graph at once, one hop a step, so numpy works on whole blocks. Queries go to
every shard while they are small; each shard returns its k best, and one
window merges them.
"""

from __future__ import annotations

import heapq
from dataclasses import dataclass, field
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from vecengine.operators.exact import BROADCAST_BYTES, topk
from vecengine.sources.io import staged

QUERY_BATCH = 256
#: Pairs of candidates that pruning compares at once.
PAIRS = 1 << 18


def encode(x: np.ndarray, bits: int, lo: np.ndarray, hi: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Codes and steps of centered rows between given bounds."""
    step = (hi - lo) / (2**bits - 1)
    safe = np.where(step > 0, step, 1.0)
    code = np.clip(np.floor((x - lo[:, None]) / safe[:, None] + 0.5), 0, 2**bits - 1)
    return np.where(step[:, None] > 0, code, 0).astype(np.uint8 if bits <= 8 else np.uint16), step


@dataclass
class Codes:
    """Rows as a codec stores them.

    ``dots`` multiplies queries and stored values without decoding: with a code
    c, its constants and the mean, q.x = q.mean + lo * sum(q) + step * (q.c), and
    a row's own square is worked out once. ``rows`` decodes a gather, ``fine``
    with the second level too; only finalists and pruning need them.
    """

    codec: str
    x: np.ndarray | None = None
    mean: np.ndarray | None = None
    lo: np.ndarray | None = None
    step: np.ndarray | None = None
    first: np.ndarray | None = None
    second: np.ndarray | None = None
    bits2: int = 0
    books: np.ndarray | None = None
    squares: np.ndarray | None = None

    @classmethod
    def of(cls, x: np.ndarray, codec: str, mean: np.ndarray | None = None) -> Codes:
        """f32, f16, pq<segments> (256 centroids each), or pv / gl with the bits of each level."""
        if codec == "f32":
            return cls(codec, x.astype(np.float32))
        if codec == "f16":
            return cls(codec, x.astype(np.float16))
        if codec[:2] == "pq":
            from vecengine.operators import pq

            made = pq.train(x[: pq.TRAIN_ROWS], int(codec[2:]), 256)
            return cls(codec, first=made.encode(x), mean=np.zeros(x.shape[1]), books=made.books)
        bits = [int(b) for b in codec[2:].split("x")]
        mean = x.mean(axis=0) if mean is None else mean
        c = x - mean
        lo, hi = (c.min(axis=1), c.max(axis=1)) if codec[:2] == "pv" else (np.full(len(c), c.min()), np.full(len(c), c.max()))
        first, step = encode(c, bits[0], lo, hi)
        out = cls(codec, None, mean, lo, step, first)
        if len(bits) == 2:
            left = c - (lo[:, None] + step[:, None] * first)
            out.second, _ = encode(left, bits[1], -step / 2, step / 2)
            out.bits2 = bits[1]
        return out

    def __len__(self) -> int:
        return len(self.x if self.x is not None else self.first)

    def rows(self, i) -> np.ndarray:
        if self.x is not None:
            return self.x[i].astype(np.float64)
        if self.books is not None:
            parts = self.books[np.arange(len(self.books)), self.first[i]]
            return parts.reshape(*parts.shape[:-2], -1)[..., : len(self.mean)]
        return self.first[i] * self.step[i][..., None] + self.lo[i][..., None] + self.mean

    def fine(self, i) -> np.ndarray:
        if self.second is None:
            return self.rows(i)
        step = self.step[i][..., None]
        return self.rows(i) + self.second[i] * (step / (2**self.bits2 - 1)) - step / 2

    def scorer(self, q: np.ndarray, kind: str, carried: np.ndarray | None = None):
        """A function (query places, row places) -> scores, in single precision from stored values alone.

        ``carried`` holds the codes of every vertex' neighbours side by side;
        the function then takes (query places, vertices, positions, row places).
        """
        if self.books is not None:
            # Look-ups: what each centroid of each segment adds.
            width = self.books.shape[2]
            parts = np.pad(q, ((0, 0), (0, self.books.shape[0] * width - q.shape[1]))).reshape(len(q), -1, 1, width)
            table = ((parts * self.books).sum(3) if kind == "ip" else -((parts - self.books) ** 2).sum(3)).astype(np.float32)
            segments = np.arange(len(self.books))

            def look(at, rows):
                s = table[at[:, None], segments, self.first[rows]].sum(axis=1)
                return s if kind == "ip" else -np.sqrt(np.maximum(-s, 0))

            return look
        if self.squares is None:
            n = len(self)
            chunks = [self.rows(slice(i, i + 65_536)) for i in range(0, n, 65_536)]
            self.squares = np.concatenate([np.empty(0), *((c * c).sum(axis=1) for c in chunks)]).astype(np.float32)
        raw = self.x if self.x is not None else self.first
        turned = q.astype(np.float32)
        own = (q * q).sum(axis=1).astype(np.float32)
        if self.x is None:
            lo, step = self.lo.astype(np.float32), self.step.astype(np.float32)
            base, total = (q @ self.mean).astype(np.float32), q.sum(axis=1).astype(np.float32)

        def run(at, *where):
            rows = where[-1]
            stored = raw[rows] if len(where) == 1 else carried[where[0], where[1]]
            dots = np.einsum("nd,nd->n", turned[at], stored.astype(np.float32, copy=False))
            if self.x is None:
                dots = base[at] + lo[rows] * total[at] + step[rows] * dots
            return dots if kind == "ip" else -np.sqrt(np.maximum(own[at] - 2 * dots + self.squares[rows], 0))

        return run


def score(a: np.ndarray, b: np.ndarray, kind: str) -> np.ndarray:
    """(m, d) against (m, c, d)."""
    if kind == "ip":
        return np.einsum("md,mcd->mc", a, b)
    diff = b - a[:, None, :]
    return -np.sqrt(np.einsum("mcd,mcd->mc", diff, diff))


@dataclass
class Graph:
    codes: Codes
    degree: int
    kind: str = "l2"
    entry: int = 0
    nbrs: np.ndarray = field(default=None)
    #: Codes of each vertex' neighbours, side by side; set by ``carry``.
    carried: np.ndarray = field(default=None)
    #: All rows decoded in single precision, while the graph is built.
    plain: np.ndarray = field(default=None)

    def __post_init__(self):
        if self.nbrs is None:
            self.nbrs = np.full((len(self.codes), self.degree), -1, np.int32)

    def carry(self) -> Graph:
        """Neighbour lists with the neighbours' codes in them: a vertex is expanded by one contiguous read, for R times the codes' memory."""
        self.carried = (self.codes.first if self.codes.x is None else self.codes.x)[np.maximum(self.nbrs, 0)]
        return self

    def search(self, q: np.ndarray, k: int, window: int, entry: np.ndarray | None = None, visited: bool = False, rerank: bool = False):
        """(ids, scores, hops, evals) of each query; missing places are -1.

        The beam is one buffer that keeps the best ``window``. Without
        ``visited`` only ids in the beam are skipped, so some vertices are scored
        again: the answers are alike. Vertices are scored from codes; the final
        beam is scored anew in double precision by what is decoded, with
        ``rerank`` by both levels.
        """
        m, w = len(q), max(window, k)
        scorer = self.codes.scorer(q, self.kind, self.carried)
        at = np.full((m, 1), self.entry) if entry is None else np.asarray(entry).reshape(m, 1)
        ids, val = np.full((m, w), -1, np.int64), np.full((m, w), -np.inf, np.float32)
        first = score(q, self.codes.rows(at), self.kind)
        ids[:, :1], val[:, :1] = np.where(np.isnan(first), -1, at), np.where(np.isnan(first), -np.inf, first)
        # Scores of what is not expanded yet, and a bound from below of the worst score in each beam.
        open_, low = val.copy(), np.full(m, -np.inf, np.float32)
        hops, evals = np.zeros(m, int), np.ones(m, int)
        # One bit a vertex: in the beam now, or with ``visited`` scored before.
        stride = len(self.codes) // 8 + 1
        bits = np.zeros(m * stride, np.uint8)
        spot = lambda who, i: (who * stride + (i >> 3), np.left_shift(1, i & 7).astype(np.uint8))
        where, bit = spot(np.arange(m), at[:, 0])
        bits[where] |= bit
        live, few = np.arange(m), min(self.degree, w)
        while True:
            some = open_ if len(live) == m else open_[live]
            pick = some.argmax(axis=1)
            go = some[np.arange(len(live)), pick] > -np.inf
            if not go.all():
                live, pick = live[go], pick[go]
            if not len(live):
                break
            node = ids[live, pick]
            open_[live, pick] = -np.inf
            hops[live] += 1
            new = self.nbrs[node].astype(np.int64)
            where, bit = spot(live[:, None], np.maximum(new, 0))
            good = (new >= 0) & ((bits[where] & bit) == 0)
            r, c = np.nonzero(good)
            rows = new[r, c]
            evals[live] += np.bincount(r, minlength=len(live))
            s = np.full(new.shape, -np.inf, np.float32)
            s[r, c] = scorer(live[r], rows) if self.carried is None else scorer(live[r], node[r], c, rows)
            if visited:
                np.bitwise_or.at(bits, where[r, c], bit[r, c])
            # Only beams that a new vertex enters change; it takes the place of one of the worst.
            r = np.flatnonzero((s > low[live][:, None]).any(axis=1))
            if not len(r):
                continue
            who, new, s = live[r], new[r], s[r]
            beam, each = val[who], np.arange(len(who))[:, None]
            place = np.argpartition(beam, few - 1, axis=1)[:, :few] if few < w else np.broadcast_to(np.arange(w), (len(r), w))
            old = beam[each, place]
            both = np.concatenate((old, s), axis=1)
            best = np.argsort(-both, axis=1, kind="stable")[:, :few]
            stays = np.zeros(both.shape, bool)
            stays[each, best] = True
            # As many leave each beam as enter it; the sort is stable, so what was there wins a tie.
            er, ec = np.nonzero(stays[:, few:])
            lr, lc = np.nonzero(~stays[:, :few])
            spots = place[lr, lc]
            if not visited:
                gone = ids[who[lr], spots]
                there = gone >= 0
                where, bit = spot(who[lr][there], gone[there])
                np.bitwise_and.at(bits, where, ~bit)
                where, bit = spot(who[er], new[er, ec])
                np.bitwise_or.at(bits, where, bit)
            ids[who[lr], spots] = new[er, ec]
            val[who[lr], spots] = open_[who[lr], spots] = s[er, ec]
            low[who] = np.minimum(both[each[:, 0], best[:, -1]], old.max(axis=1))
        decoded = self.codes.fine if rerank else self.codes.rows
        val = np.where(ids >= 0, score(q, decoded(np.maximum(ids, 0)), self.kind), -np.inf)
        order = np.lexsort((ids, -val), axis=1)[:, :k]
        return np.take_along_axis(ids, order, axis=1), np.take_along_axis(val, order, axis=1), hops, evals

    def search_heap(self, q: np.ndarray, k: int, window: int):
        """(ids, scores) of one query, with two heaps in place of the buffer: the same answer."""
        w, scorer, zero = max(window, k), self.codes.scorer(q[None], self.kind), np.zeros(1, np.int64)
        best = float(scorer(zero, np.array([self.entry]))[0])
        open_, beam, seen = [(-best, self.entry)], [(best, -self.entry)], {self.entry}
        while open_:
            far, node = heapq.heappop(open_)
            if len(beam) == w and -far < beam[0][0]:
                break
            new = np.array([v for v in self.nbrs[node].tolist() if v >= 0 and v not in seen], np.int64)
            seen.update(new.tolist())
            for v, s in zip(new.tolist(), scorer(np.zeros(len(new), np.int64), new).tolist() if len(new) else (), strict=True):
                if len(beam) < w or (s, -v) > beam[0]:
                    heapq.heappush(open_, (-s, v))
                    (heapq.heappush if len(beam) < w else heapq.heapreplace)(beam, (s, -v))
        ids = np.array([-v for _, v in beam])
        val = score(q[None], self.codes.rows(ids[None]), self.kind)[0]
        order = np.lexsort((ids, -val))[:k]
        return ids[order], val[order]

    def prune(self, src: np.ndarray, cands: np.ndarray, alpha: float) -> np.ndarray:
        """Kept candidates (-1 filled) of each source; repeated ones and the source itself never count."""
        none = len(self.codes)
        cands = np.sort(cands, axis=1)
        cands[:, 1:][cands[:, 1:] == cands[:, :-1]] = none
        cands[(cands == src[:, None]) | (cands < 0)] = none
        cands.sort(axis=1)
        each = (cands < none).sum(axis=1)
        kept = np.full((len(src), self.degree), -1, np.int64)
        # Sources with like numbers of candidates go together, the most first.
        order = np.argsort(-each, kind="stable")
        at = 0
        while at < len(order) and each[order[at]]:
            wide = int(each[order[at]])
            part = order[at : at + max(1, min(256, PAIRS // wide**2))]
            kept[part] = self._prune(src[part], np.where(cands[part, :wide] < none, cands[part, :wide], -1), alpha)
            at += len(part)
        return kept

    def _prune(self, src: np.ndarray, cands: np.ndarray, alpha: float) -> np.ndarray:
        plain = (lambda i: self.codes.rows(i).astype(np.float32)) if self.plain is None else self.plain.__getitem__
        x = plain(np.maximum(cands, 0))
        own = score(plain(src), x, self.kind)
        own[cands < 0] = -np.inf
        order, each = np.lexsort((cands, -own), axis=1), np.arange(len(src))[:, None]
        cands, own, x = cands[each, order], own[each, order], x[each, order]
        norms = np.sqrt(np.einsum("md,md->m", plain(src), plain(src)) * np.einsum("mcd,mcd->mc", x, x).max(axis=1))
        covers = self._covers(x, own, cands >= 0, alpha, norms)
        alive, rows, kept = cands >= 0, np.arange(len(src)), np.full((len(src), self.degree), -1, np.int64)
        for r in range(self.degree):
            some = alive.any(axis=1)
            if not some.any():
                break
            best = np.argmax(alive, axis=1)
            kept[some, r] = cands[rows, best][some]
            # The winner goes by itself: an inner product need not cover its own.
            alive[rows, best] = False
            alive &= ~covers[rows, best]
        return kept

    def _covers(self, x: np.ndarray, own: np.ndarray, valid: np.ndarray, alpha: float, rounds: np.ndarray) -> np.ndarray:
        """(sources, i, j): alpha times the score of candidates i < j reaches the source's own score of j.

        Products of all pairs decide; those that single precision might decide
        otherwise are scored one by one, so the answer is that of ``score``.
        """
        dots, mine = x @ x.transpose(0, 2, 1), np.where(valid, own, 0)[:, None, :]
        squares = np.einsum("mcc->mc", dots)
        total = np.maximum(squares[:, :, None], squares[:, None, :])
        if self.kind == "ip":
            # Candidates do not tell the source's own norm; their scores round with it.
            gap, most = alpha * dots - mine, alpha * total + np.abs(mine) + rounds[:, None, None]
        else:
            mine = mine * mine
            far = (alpha * alpha) * (squares[:, :, None] + squares[:, None, :] - 2 * dots)
            gap, most = mine - far, mine + (2 * alpha * alpha) * total
        covers = gap >= 0
        near = ~(np.abs(gap) > (4 + x.shape[2]) * 2.4e-7 * most) & valid[:, None, :]
        r, i, j = np.nonzero(near & np.triu(np.ones(near.shape[1:], bool), 1))
        step = max(1, (1 << 22) // x.shape[2])
        for at in range(0, len(r), step):
            a, b, c = (one[at : at + step] for one in (r, i, j))
            covers[a, b, c] = alpha * score(x[a, b], x[a, c][:, None, :], self.kind)[:, 0] >= own[a, c]
        return covers

    def build(self, window: int, alphas: tuple[float, ...] = (1.0, 1.2), batch: int = 128) -> Graph:
        """Insert all rows by search and pruning, in batches that double, once for each alpha."""
        n = len(self.codes)
        self.plain = self.codes.x if self.codes.codec == "f32" else self.codes.rows(np.arange(n)).astype(np.float32)
        middle = self.codes.rows(np.arange(n)).mean(axis=0)
        self.entry = int(np.argmin(((self.codes.rows(np.arange(n)) - middle) ** 2).sum(axis=1))) if n else 0
        for turn, alpha in enumerate(alphas):
            at, size = 0, 1 if turn == 0 else batch
            while at < n:
                ids = np.arange(at, min(n, at + size))
                q = self.codes.rows(ids)
                found, *_ = self.search(q, window, window)
                mates = np.broadcast_to(ids, (len(ids), len(ids)))
                near = np.argsort(-score(q, np.broadcast_to(q, (len(q), *q.shape)), self.kind), axis=1)[:, : window + 1]
                self._link(ids, np.concatenate((found, np.take_along_axis(mates, near, axis=1), self.nbrs[ids]), axis=1), alpha)
                at, size = at + size, min(batch, size * 2)
        self.plain = None
        return self

    def _link(self, ids: np.ndarray, cands: np.ndarray, alpha: float) -> None:
        self.nbrs[ids] = self.prune(ids, cands, alpha)
        src = np.repeat(ids, self.degree)
        dst = self.nbrs[ids].ravel().astype(np.int64)
        src, dst = src[dst >= 0], dst[dst >= 0]
        known = (self.nbrs[dst] == src[:, None]).any(axis=1)
        src, dst = src[~known], dst[~known]
        if not len(dst):
            return
        order = np.argsort(dst, kind="stable")
        src, dst = src[order], dst[order]
        ends, start, extra = np.unique(dst, return_index=True, return_counts=True)
        have = (self.nbrs[ends] >= 0).sum(axis=1)
        c = np.full((len(ends), max(self.degree, (have + extra).max())), -1, np.int64)
        c[:, : self.degree] = self.nbrs[ends]
        c[np.repeat(np.arange(len(ends)), extra), np.arange(len(dst)) + np.repeat(have - start, extra)] = src
        full = have + extra > self.degree
        self.nbrs[ends[~full]] = c[~full, : self.degree]
        self.nbrs[ends[full]] = self.prune(ends[full], c[full], alpha)


@dataclass
class Layers:
    """A hierarchy: every level a graph over fewer rows; greedy above, a beam at the base."""

    graphs: list[Graph]
    rows: list[np.ndarray]

    @classmethod
    def build(cls, codes_of, ids: np.ndarray, degree: int, window: int, kind: str = "l2") -> Layers:
        # A row reaches level l if its scrambled id has l zero digits: geometric, and the same everywhere.
        mixed = (ids.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(32)
        base = max(2, degree // 2)
        graphs, rows, keep, scale = [], [], np.arange(len(ids)), 1
        while len(keep) > 1 or (len(keep) and not graphs):
            graphs.append(Graph(codes_of(keep), degree if scale == 1 else base, kind).build(window, (1.0,)))
            rows.append(keep)
            scale *= base
            keep = keep[mixed[keep] % np.uint64(scale) == 0]
        return cls(graphs, rows)

    def search(self, q: np.ndarray, k: int, window: int):
        entry, evals = None, np.zeros(len(q), int)
        for level in range(len(self.graphs) - 1, 0, -1):
            found, _, _, e = self.graphs[level].search(q, 1, 1, entry)
            evals += e
            # A row of a level stands in the level below at its own place there.
            entry = np.searchsorted(self.rows[level - 1], self.rows[level][found[:, 0]])
        ids, val, hops, e = self.graphs[0].search(q, k, window, entry)
        return ids, val, hops, evals + e


_SCHEMA = "shard int, n int, d int, kind string, codec string, degree int, entry int, ids binary, first binary, second binary, lo binary, step binary, mean binary, nbrs binary, books binary"


def build_index(db: DataFrame, codec: str = "pv8", degree: int = 16, window: int = 32, alphas: tuple[float, ...] = (1.0, 1.2), kind: str = "l2", mean: list[float] | None = None, search_codec: str | None = None, shard: str = "shard") -> DataFrame:
    """One row for each shard of ``db(shard, id, vec)``: its graph, built from codes.

    ``search_codec`` may differ from the codec the graph is built from. A shard
    must fit one task: ``planner.deal`` bounds its rows and bytes.
    """
    mu = None if mean is None else np.asarray(mean)

    def run(t: pa.Table) -> pa.Table:
        ids = t.column("id").to_numpy()
        order = np.argsort(ids, kind="stable")
        x = t.column("vec").combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(len(ids), -1)[order]
        g = Graph(Codes.of(x, codec, mu), degree, kind).build(window, alphas)
        c = g.codes if search_codec in (None, codec) else Codes.of(x, search_codec, mu)
        raw = lambda a: None if a is None else np.ascontiguousarray(a).tobytes()
        row = [int(t.column("shard")[0].as_py()), len(ids), x.shape[1], kind, c.codec, degree, g.entry, raw(ids[order]), raw(c.x if c.x is not None else c.first), raw(c.second), raw(c.lo), raw(c.step), raw(c.mean), raw(g.nbrs), raw(c.books)]
        names = [f.split()[0] for f in _SCHEMA.split(", ")]
        kinds = {"int": pa.int32(), "string": pa.string(), "binary": pa.binary()}
        return pa.table({n: pa.array([v], kinds[f.split()[1]]) for n, v, f in zip(names, row, _SCHEMA.split(", "), strict=True)})

    return db.select(F.col(shard).cast("int").alias("shard"), F.col("id").cast("long"), F.col("vec").cast("array<double>")).groupBy("shard").applyInArrow(run, _SCHEMA)


def _open(row) -> tuple[np.ndarray, Graph]:
    ids = np.frombuffer(row["ids"], np.int64)
    shape = (row["n"], row["d"])
    codec = row["codec"]
    if codec[:2] == "pq":
        books = np.frombuffer(row["books"])
        mean = np.frombuffer(row["mean"])
        segments = int(codec[2:])
        codes = Codes(codec, first=np.frombuffer(row["first"], np.uint8).reshape(row["n"], -1), mean=mean, books=books.reshape(segments, -1, -(-len(mean) // segments)))
    elif codec in ("f32", "f16"):
        codes = Codes(codec, np.frombuffer(row["first"], np.float32 if codec == "f32" else np.float16).reshape(shape))
    else:
        bits = [int(b) for b in codec[2:].split("x")]
        kind = lambda b: np.uint8 if b <= 8 else np.uint16
        codes = Codes(codec, None, np.frombuffer(row["mean"]), np.frombuffer(row["lo"]), np.frombuffer(row["step"]), np.frombuffer(row["first"], kind(bits[0])).reshape(shape))
        if row["second"] is not None:
            codes.second, codes.bits2 = np.frombuffer(row["second"], kind(bits[1])).reshape(shape), bits[1]
    return ids, Graph(codes, row["degree"], row["kind"], row["entry"], np.frombuffer(row["nbrs"], np.int32).reshape(row["n"], -1))


def edges_of(index: DataFrame) -> DataFrame:
    """(shard, src, id) of a built index."""

    def run(batches):
        for batch in batches:
            for row in batch.to_pylist():
                ids, nbrs = np.frombuffer(row["ids"], np.int64), np.frombuffer(row["nbrs"], np.int32).reshape(row["n"], -1)
                src, pos = np.nonzero(nbrs >= 0)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(src), row["shard"], np.int32)), pa.array(ids[src]), pa.array(ids[nbrs[src, pos]])], ["shard", "src", "id"])

    return index.select("shard", "n", "ids", "nbrs").mapInArrow(run, "shard int, src long, id long")


def search_index(index: DataFrame, q: DataFrame, k: int, window: int, rerank: bool = False, visited: bool = False, carry: bool = False, batch: int = QUERY_BATCH, parts: int = 1) -> DataFrame:
    """(qid, rank, id, score, hops, evals): every shard searched, best k of all.

    hops and evals sum over shards. With ``rerank`` the final beam is scored
    anew by both levels; the second level is not read before. ``carry`` searches
    with the neighbours' codes in the lists. ``batch`` queries move together; 1
    takes them one at a time. Queries are sent to all tasks in blocks of a
    bounded size, one scan of the index for each. So many ``parts`` of tasks
    share the batches of a shard; each reads the index, which must then be a
    stored table.
    """
    spark = q.sparkSession
    asks = q.select(F.col("qid").cast("long"), F.col("vec").cast("array<double>"))
    shape = asks.agg(F.count("vec").alias("m"), F.max(F.size("vec")).alias("d")).first()
    if not shape["m"]:
        return spark.createDataFrame([], "qid long, rank int, id long, score double, hops long, evals long")
    blocks = max(1, -(-shape["m"] * shape["d"] * 8 // BROADCAST_BYTES))
    columns = [c for c in index.columns if rerank or c != "second"]

    def found_by(got) -> DataFrame:
        sent = spark.sparkContext.broadcast((got["qid"].to_numpy(), np.stack(got["vec"].to_numpy())))

        def run(batches, part):
            qids, qs = sent.value
            for rows in batches:
                for i in range(rows.num_rows):
                    row = {c: rows.column(j)[i] for j, c in enumerate(columns)}
                    # Large cells are read in place, not copied.
                    row = {"second": None} | {c: (v.as_buffer() if v.is_valid else None) if pa.types.is_binary(v.type) else v.as_py() for c, v in row.items()}
                    ids, g = _open(row)
                    g = g.carry() if carry else g
                    for at in range(part * batch, len(qs), parts * batch):
                        found, val, hops, evals = g.search(qs[at : at + batch], min(k, len(ids)), window, visited=visited, rerank=rerank)
                        r, c = np.nonzero(found >= 0)
                        yield pa.RecordBatch.from_arrays([pa.array(qids[at : at + batch][r]), pa.array(ids[found[r, c]]), pa.array(val[r, c]), pa.array(np.where(c == 0, hops[r], 0)), pa.array(np.where(c == 0, evals[r], 0))], ["qid", "id", "score", "hops", "evals"])

        out = None
        for part in range(parts):
            one = index.select(*columns).mapInArrow(partial(run, part=part), "qid long, id long, score double, hops long, evals long")
            out = one if out is None else out.union(one)
        return out

    found = None
    for block in range(blocks):
        mine = asks if blocks == 1 else asks.where(F.pmod(F.xxhash64("qid"), F.lit(blocks)) == block)
        # Kept, for answers and costs both come from it: else every shard would be searched again for each use.
        one = staged(found_by(mine.toPandas().dropna()), "found")
        found = one if found is None else found.union(one)
    cost = found.groupBy("qid").agg(F.sum("hops").alias("hops"), F.sum("evals").alias("evals"))
    return topk(found.select("qid", "id", "score"), k).join(cost, "qid").select("qid", "rank", "id", "score", "hops", "evals")


def search_layers(db: DataFrame, q: DataFrame, k: int, windows: tuple[int, ...], degree: int, build_window: int, kind: str = "l2", shard: str = "shard") -> DataFrame:
    """(window, qid, rank, id, score, evals) by a hierarchy of graphs for each shard of ``db(shard, id, vec)``, built and searched in one task."""
    asks = q.select(F.col("qid").cast("long"), F.col("vec").cast("array<double>")).toPandas().dropna()
    if len(asks) and len(asks) * len(asks["vec"].iloc[0]) * 8 > BROADCAST_BYTES:
        raise ValueError("the queries of one build must fit a broadcast")
    sent = db.sparkSession.sparkContext.broadcast((asks["qid"].to_numpy(), np.stack(asks["vec"].to_numpy())))

    def run(t: pa.Table) -> pa.Table:
        qids, qs = sent.value
        ids = t.column("id").to_numpy()
        order = np.argsort(ids, kind="stable")
        x = t.column("vec").combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(len(ids), -1)[order]
        layers, out = Layers.build(lambda keep: Codes.of(x[keep], "f32"), ids[order], degree, build_window, kind), []
        for w in windows:
            found, val, _, evals = layers.search(qs, min(k, len(ids)), w)
            r, c = np.nonzero(found >= 0)
            out.append(pa.table({"window": pa.array(np.full(len(r), w, np.int32)), "qid": qids[r], "id": ids[order][found[r, c]], "score": val[r, c], "evals": np.where(c == 0, evals[r], 0)}))
        return pa.concat_tables(out)

    found = db.select(F.col(shard).cast("int").alias("shard"), F.col("id").cast("long"), F.col("vec").cast("array<double>")).groupBy("shard").applyInArrow(run, "window int, qid long, id long, score double, evals long")
    best = Window.partitionBy("window", "qid").orderBy(F.desc("score"), "id")
    every = Window.partitionBy("window", "qid")
    ranked = found.withColumn("rank", F.row_number().over(best)).withColumn("evals", F.sum("evals").over(every))
    return ranked.where(F.col("rank") <= k).select("window", "qid", "rank", "id", "score", "evals")
