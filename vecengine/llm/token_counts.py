"""Edit-aware token counts.

A document is kept with a segment tree over leaves of a bounded number of
pre-tokens: characters and tokens of each leaf are stored as two arrays beside
the text, and the sums above them follow from those. An edit goes down the tree
by characters, splits anew only the touched leaves plus the context at their
borders, re-encodes only those, and mends the sums on the paths to the root.
Edited trees are written back as the same columns, so that later edits start
from them and no text is encoded twice.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecengine.llm.bpe import Bpe, codec
from vecengine.llm.common import small_batches, staged

#: A pre-token's end may depend on this many characters behind it ("'l" + "l").
LOOKAHEAD = 2
LEAF = 32
EDITS = "array<struct<at:int,del:int,ins:string>>"
_KEPT = "text string, n_chars long, n_tokens long, leaf_chars array<int>, leaf_tokens array<int>"


def leaves_of(text: str, bpe: Bpe) -> tuple[np.ndarray, np.ndarray, int]:
    """Characters and tokens of each leaf, and the number of pre-tokens."""
    pieces = bpe.split(text)
    if not pieces:
        return np.zeros(1, np.int32), np.zeros(1, np.int32), 0
    at = np.arange(0, len(pieces), LEAF)
    chars = np.fromiter(map(len, pieces), np.int64, len(pieces))
    tokens = np.fromiter(map(len, map(bpe.words.__getitem__, pieces)), np.int64, len(pieces)) // 4
    return np.add.reduceat(chars, at).astype(np.int32), np.add.reduceat(tokens, at).astype(np.int32), len(pieces)


class TokenTree:
    """``chars`` and ``tokens``: what an earlier tree of this text stored; without them the text is encoded."""

    def __init__(self, text: str, bpe: Bpe, chars=None, tokens=None):
        if any(s in text for s in bpe.special):
            raise ValueError("a text with special tokens is counted afresh")
        self.bpe, self.encoded, self.source = bpe, 0, text
        if chars is None:
            chars, tokens, self.encoded = leaves_of(text, bpe)
        starts = np.concatenate(([0], np.cumsum(chars)[:-1]))
        #: A leaf that no edit touched is its place in the source; else its pre-tokens and their counts.
        self.leaves: list = starts.tolist()
        self._grow(list(zip(map(int, chars), map(int, tokens), strict=True)))

    def _count(self, piece: str) -> int:
        self.encoded += 1
        return len(self.bpe.words[piece]) // 4

    def _grow(self, level: list[tuple[int, int]]) -> None:
        """Sums bottom-up: levels[0] per leaf, the last level is the root."""
        self.levels = [level]
        while len(level) > 1:
            level = [(sum(x[0] for x in level[i : i + 2]), sum(x[1] for x in level[i : i + 2])) for i in range(0, len(level), 2)]
            self.levels.append(level)

    @property
    def n_tokens(self) -> int:
        return self.levels[-1][0][1]

    @property
    def n_chars(self) -> int:
        return self.levels[-1][0][0]

    @property
    def text(self) -> str:
        return "".join(self.source[x : x + n[0]] if isinstance(x, int) else "".join(x[0]) for x, n in zip(self.leaves, self.levels[0], strict=True))

    def stored(self) -> tuple[list[int], list[int]]:
        return [n[0] for n in self.levels[0]], [n[1] for n in self.levels[0]]

    def _open(self, k: int) -> list:
        """Pre-tokens and counts of a leaf. It begins at a border, and what follows it can only move its last borders, so that context is split with it."""
        leaf = self.leaves[k]
        if not isinstance(leaf, int):
            return leaf
        end, pieces, at = leaf + self.levels[0][k][0], [], leaf
        for piece in self.bpe.split(self.source[leaf : end + LOOKAHEAD]):
            if at >= end:
                break
            pieces.append(piece)
            at += len(piece)
        self.leaves[k] = [pieces, [self._count(p) for p in pieces]]
        return self.leaves[k]

    def _find(self, at: int) -> tuple[int, int]:
        """Leaf that holds character ``at``, and the leaf's first character."""
        node, start = 0, 0
        for level in reversed(self.levels[:-1]):
            node *= 2
            if at >= start + level[node][0] and node + 1 < len(level):
                start += level[node][0]
                node += 1
        return node, start

    def _mend(self, leaf: int) -> None:
        pieces, counts = self.leaves[leaf]
        self.levels[0][leaf] = (sum(map(len, pieces)), sum(counts))
        for below, level in zip(self.levels, self.levels[1:], strict=False):
            leaf //= 2
            pair = below[2 * leaf : 2 * leaf + 2]
            level[leaf] = (sum(x[0] for x in pair), sum(x[1] for x in pair))

    def edit(self, at: int, delete: int, insert: str) -> None:
        """Replace ``delete`` characters from ``at`` on by ``insert``.

        Places beyond the text mean its end. The region starts at the first
        pre-token that may have looked as far as ``at`` and ends where a new
        border meets an old one behind the edit, for from there on the text,
        and so its split, is the old one.
        """
        at = max(0, min(at, self.n_chars))
        delete = max(0, min(delete, self.n_chars - at))
        first, start = self._find(max(0, at - 1))
        while first > 0 and start + LOOKAHEAD > at - 1:  # the leaf before may have looked in
            first -= 1
            start -= self.levels[0][first][0]
        pieces, counts = self._open(first)
        skip, begin = 0, start
        while skip < len(pieces) and begin + len(pieces[skip]) + LOOKAHEAD <= at:
            begin += len(pieces[skip])
            skip += 1
        last, old = first, "".join(pieces[skip:])
        ends = _ends(pieces[skip:], begin)
        while True:
            while begin + len(old) < at + delete and last + 1 < len(self.leaves):
                last, old, ends = self._take(last, old, ends, begin)
            fresh = old[: at - begin] + insert + old[at - begin + delete :]
            shift, final = len(insert) - delete, last + 1 == len(self.leaves)
            kept, meet, place = [], None, begin
            for piece in self.bpe.split(fresh):
                # Borders near the end of what was taken are not certain yet.
                if place - shift in ends and place >= at + len(insert) and (final or place <= begin + len(fresh) - LOOKAHEAD):
                    meet = place
                    break
                place += len(piece)
                kept.append(piece)
            if meet is not None or final:
                break
            last, old, ends = self._take(last, old, ends, begin)
        tail = self._behind(first, skip, last, begin, meet, shift)
        known = dict(zip(pieces[skip:], counts[skip:], strict=True))
        new = [*zip(pieces[:skip], counts[:skip], strict=True), *((p, known[p] if p in known else self._count(p)) for p in kept), *tail]
        span = last + 1 - first
        if len(new) <= 2 * LEAF * span:
            # The same leaves share the pre-tokens, and only their paths to the root change.
            each = -(-len(new) // span) if new else 0
            for k in range(span):
                part = new[k * each : (k + 1) * each]
                self.leaves[first + k] = [[p for p, _ in part], [c for _, c in part]]
                self._mend(first + k)
            return
        parts = [new[i : i + LEAF] for i in range(0, len(new), LEAF)]
        self.leaves[first : last + 1] = [[[p for p, _ in part], [c for _, c in part]] for part in parts]
        self._grow([*self.levels[0][:first], *((sum(len(p) for p, _ in part), sum(c for _, c in part)) for part in parts), *self.levels[0][last + 1 :]])

    def _take(self, last: int, old: str, ends: set[int], begin: int):
        pieces = self._open(last + 1)[0]
        return last + 1, old + "".join(pieces), ends | _ends(pieces, begin + len(old))

    def _behind(self, first: int, skip: int, last: int, begin: int, meet: int | None, shift: int) -> list[tuple[str, int]]:
        """Old pre-tokens and counts, in the leaves taken, from the meeting place on."""
        out, place = [], begin
        for k in range(first, last + 1) if meet is not None else ():
            for i, (piece, count) in enumerate(zip(*self.leaves[k], strict=True)):
                if k == first and i < skip:
                    continue
                if place >= meet - shift:
                    out.append((piece, count))
                place += len(piece)
        return out


def _ends(pieces: list[str], start: int) -> set[int]:
    out = {start}
    for piece in pieces:
        start += len(piece)
        out.add(start)
    return out


def grow(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text", keep: tuple[str, ...] = ()) -> DataFrame:
    """(id, *keep, text, n_chars, n_tokens, leaf_chars, leaf_tokens, n_pretokens): the trees of all documents, one row per input row.

    Null texts count as empty. Texts with special tokens have no tree (null
    arrays): they are counted afresh. Narrow.
    """
    small_batches(docs.sparkSession)

    def run(batches):
        bpe = codec(path)
        for batch in batches:
            out = []
            for text in batch.column(width):
                text = text.as_py() or ""
                if any(s in text for s in bpe.special):
                    out.append((text, len(text), len(bpe.encode(text)) // 4, None, None, len(bpe.split(text))))
                else:
                    chars, tokens, n = leaves_of(text, bpe)
                    out.append((text, len(text), int(tokens.sum()), chars, tokens, n))
            yield _batch(batch, width, out, "n_pretokens")

    width = 1 + len(keep)
    slim = docs.select(F.col(id_col).cast("long").alias(id_col), *keep, F.col(text_col).cast("string").alias("__text"))
    return slim.mapInArrow(run, f"{_kinds(slim, width)}, {_KEPT}, n_pretokens long")


def edit(trees: DataFrame, path: str, edits_col: str, id_col: str = "doc_id", keep: tuple[str, ...] = ()) -> DataFrame:
    """(id, *keep) and the trees after ``edits_col`` (array<struct<at int, del int, ins string>>, applied in turn), and n_encoded.

    ``trees`` are rows of ``grow`` or of this function. n_encoded is the number
    of pre-tokens that were encoded; it is null where a text with special
    tokens, or edits that insert them, were counted afresh. Null edits and null
    fields of edits change nothing. Narrow: one pass over the stored trees.
    """
    small_batches(trees.sparkSession)

    def run(batches):
        bpe = codec(path)
        for batch in batches:
            texts, chars, tokens, asked = (batch.column(width + i) for i in range(4))
            out = []
            for i, edits in enumerate(asked.to_pylist()):
                text, edits = texts[i].as_py() or "", [(e["at"] or 0, e["del"] or 0, e["ins"] or "") for e in edits or [] if e]
                if not chars[i].is_valid or any(s in e[2] for s in bpe.special for e in edits):
                    text = _afresh(text, edits)
                    if any(s in text for s in bpe.special):
                        out.append((text, len(text), len(bpe.encode(text)) // 4, None, None, None))
                    else:
                        c, n, _ = leaves_of(text, bpe)
                        out.append((text, len(text), int(n.sum()), c, n, None))
                    continue
                tree = TokenTree(text, bpe, chars[i].values.to_numpy(), tokens[i].values.to_numpy())
                for e in edits:
                    tree.edit(*e)
                # Edits may have put a special token together.
                text = tree.text if edits else text
                if any(s in text for s in bpe.special):
                    out.append((text, len(text), len(bpe.encode(text)) // 4, None, None, None))
                else:
                    out.append((text, tree.n_chars, tree.n_tokens, *tree.stored(), tree.encoded))
            yield _batch(batch, width, out, "n_encoded")

    width = 1 + len(keep)
    slim = trees.select(id_col, *keep, F.col("text").alias("__text"), F.col("leaf_chars").alias("__chars"), F.col("leaf_tokens").alias("__tokens"), F.col(edits_col).cast(EDITS).alias("__edits"))
    return slim.mapInArrow(run, f"{_kinds(slim, width)}, {_KEPT}, n_encoded long")


def _kinds(df: DataFrame, width: int) -> str:
    return ", ".join(f"`{n}` {t}" for n, t in df.dtypes[:width])


def _batch(batch: pa.RecordBatch, width: int, out: list[tuple], name: str) -> pa.RecordBatch:
    cols = list(zip(*out, strict=True)) or [[]] * 6
    kinds = [pa.string(), pa.int64(), pa.int64(), pa.list_(pa.int32()), pa.list_(pa.int32()), pa.int64()]
    names = [*batch.schema.names[:width], "text", "n_chars", "n_tokens", "leaf_chars", "leaf_tokens", name]
    return pa.RecordBatch.from_arrays([*(batch.column(i) for i in range(width)), *(pa.array(c, k) for c, k in zip(cols, kinds, strict=True))], names)


def _afresh(text: str, edits) -> str:
    for at, delete, insert in edits:
        at = max(0, min(at, len(text)))
        text = text[:at] + insert + text[at + max(0, delete) :]
    return text


def count_tokens(docs: DataFrame, path: str, edits_col: str | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Token counts before and after edits: (id, n_chars, n_pretokens, n_tokens, n_tokens_after, n_encoded), one row per input row.

    The trees are grown once and kept as a table; the edits then start from the
    stored trees. Without ``edits_col`` nothing is edited. An empty table gives
    an empty result; repeated rows and ids each count by themselves.
    """
    edits = (F.col(edits_col) if edits_col else F.lit(None)).cast(EDITS)
    slim = docs.select(F.col(id_col).cast("long").alias("__id"), edits.alias("__asked"), F.col(text_col).cast("string").alias("__doc"))
    trees = grow(slim, path, "__id", "__doc", ("__asked",))
    if edits_col is None:
        return trees.select(F.col("__id").alias(id_col), "n_chars", "n_pretokens", "n_tokens", F.col("n_tokens").alias("n_tokens_after"), F.lit(0).cast("long").alias("n_encoded"))
    kept = staged(trees, "token-trees").withColumnsRenamed({"n_chars": "__chars_then", "n_tokens": "__tokens_then"})
    after = edit(kept, path, "__asked", "__id", ("__chars_then", "n_pretokens", "__tokens_then"))
    return after.select(F.col("__id").alias(id_col), F.col("__chars_then").alias("n_chars"), "n_pretokens", F.col("__tokens_then").alias("n_tokens"), F.col("n_tokens").alias("n_tokens_after"), "n_encoded")
