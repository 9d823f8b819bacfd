"""Exact byte-level BPE by dynamic programming over prefixes.

For every prefix of a pre-token there is one and only one token that ends its
encoding. A candidate is any vocabulary entry that ends at that place (found
by a suffix automaton over the vocabulary); it is the right one if it may stand
beside the last token of the prefix before it. Following the back-pointers from
the end yields the ids. The cost is linear in the length of the pre-token, also
for one of many megabytes, while repeated merging is not.
"""

from __future__ import annotations

import base64
import hashlib
import json
import re
import sys
import unicodedata
from functools import lru_cache

import ahocorasick
import numpy as np
import pyarrow as pa
import regex
import tiktoken
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from tokenizers import Tokenizer

#: The split pattern of this family of byte-level vocabularies.
SPLIT = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
#: Texts of code points below this one are split by the quicker re module, its classes spelled out.
_NEAR = 0x250
_MEMO_WORDS, _MEMO_LENGTH, _MEMO_PAIRS = 400_000, 64, 1_000_000


def _near_pattern() -> str:
    """SPLIT with its classes as sets of the code points below _NEAR."""
    points = [chr(c) for c in range(_NEAR)]
    own = lambda found: "".join(re.escape(c) for c in found)
    letters, numbers = (own(c for c in points if unicodedata.category(c)[0] == kind) for kind in "LN")
    space = own(regex.findall(r"\s", "".join(points)))
    return SPLIT.replace(r"[^\s\p{L}\p{N}]", f"[^{space}{letters}{numbers}]").replace(r"\p{L}", f"[{letters}]").replace(r"\p{N}", f"[{numbers}]").replace(r"\S", f"[^{space}]").replace(r"\s", f"[{space}]")


def byte_letters() -> dict[str, int]:
    """The printable letter that stands for each byte in the vocabulary file."""
    shown = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or 174 <= b]
    letters = {chr(b): b for b in shown}
    letters.update({chr(256 + i): b for i, b in enumerate(b for b in range(256) if b not in set(shown))})
    return letters


class _Words(dict):
    """Ids of short pre-tokens, as little-endian 32-bit integers; bounded."""

    def __init__(self, encode):
        super().__init__()
        self.encode = encode

    def __missing__(self, word: str) -> bytes:
        ids = np.asarray(self.encode(word.encode()), "<u4").tobytes()
        if len(word) <= _MEMO_LENGTH:
            if len(self) >= _MEMO_WORDS:
                self.clear()
            self[word] = ids
        return ids


class Bpe:
    def __init__(self, path: str):
        self.path = path
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        letters = byte_letters()
        vocab = spec["model"]["vocab"]
        size = 1 + max([*vocab.values(), *(t["id"] for t in spec["added_tokens"])])
        self.text = [b""] * size
        for token, i in vocab.items():
            self.text[i] = bytes(letters[c] for c in token)
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        for token, i in self.special.items():
            self.text[i] = token.encode()
        self.rank, self.left, self.right, self.pairs = [-1] * size, [-1] * size, [-1] * size, {}
        for r, merge in enumerate(spec["model"]["merges"]):
            a, b = merge.split(" ") if isinstance(merge, str) else merge
            x, y, z = vocab[a], vocab[b], vocab[a + b]
            self.pairs.setdefault((x, y), r)
            if self.rank[z] < 0:
                self.rank[z], self.left[z], self.right[z] = r, x, y
        self.automaton = ahocorasick.Automaton()
        for token, i in vocab.items():
            if token not in self.special and (self.rank[i] < 0) == (len(self.text[i]) == 1) and self._stands(i):
                raw = self.text[i].decode("latin-1")
                self.automaton.add_word(raw, (i, len(raw)))
        self.automaton.make_automaton()
        #: Every suffix of a vocabulary entry is a state: its own id, or -1.
        self.entry = {raw: token for raw, (token, _) in self.automaton.items()}
        self.states = dict.fromkeys((raw[k:] for raw in self.entry for k in range(1, len(raw))), -1) | self.entry
        self.fits: dict[int, bool] = {}
        self.words = _Words(self.encode_word)
        self.find, self.find_near = regex.compile(SPLIT).findall, re.compile(_near_pattern()).findall
        self.find_new = None
        self.apart = regex.compile("|".join(f"({regex.escape(s)})" for s in self.special)) if self.special else None

    def _clash(self, x: int, y: int, until: int) -> bool:
        """Whether a merge across the border of x and y comes before ``until``.

        Looks back in time: of the two pieces at the border, the one that was
        made later is taken apart, and its making is the new deadline. Equal
        merges go from left to right, so the piece on the right counts as later.
        """
        rank, pairs = self.rank, self.pairs
        while True:
            r = pairs.get((x, y))
            if r is not None and r < until:
                return True
            if rank[x] > rank[y]:
                until, x = rank[x], self.right[x]
            elif rank[y] >= 0:
                until, y = rank[y] + 1, self.left[y]
            else:
                return False

    def _stands(self, i: int) -> bool:
        """Whether the encoding of the token's own bytes is that token."""
        return self.rank[i] < 0 or not self._clash(self.left[i], self.right[i], self.rank[i])

    def _beside(self, x: int, y: int) -> bool:
        key = x << 24 | y
        if len(self.fits) >= _MEMO_PAIRS:
            self.fits.clear()
        known = self.fits[key] = not self._clash(x, y, 1 << 60)
        return known

    def encode_word(self, word: bytes) -> list[int]:
        raw = word.decode("latin-1")
        if raw in self.entry:
            return [self.entry[raw]]
        last = self._last_of_all(raw) if len(raw) > _MEMO_LENGTH else {}
        if not last:
            self._last_of(raw, len(raw), last)
        out, end, text = [], len(raw), self.text
        while end:
            token = last[end]
            out.append(token)
            end -= len(text[token])
        return out[::-1]

    def _last_of(self, raw: str, end: int, last: dict[int, int]) -> int:
        """The last token of the prefix ``raw[:end]``; fills ``last``.

        Only the prefixes that a candidate asks for are worked out, each once.
        """
        states, start, found = self.states, end - 1, []
        while start >= 0:
            token = states.get(raw[start:end])
            if token is None:
                break
            if token >= 0:
                found.append(token)
                found.append(start)
            start -= 1
        fits = self.fits
        while found:
            start = found.pop()
            token = found.pop()
            if start:
                before = last.get(start)
                if before is None:
                    before = self._last_of(raw, start, last)
                fit = fits.get(before << 24 | token)
                if not (self._beside(before, token) if fit is None else fit):
                    continue
            last[end] = token
            return token
        raise ValueError("the vocabulary lacks a byte")

    def _last_of_all(self, raw: str) -> dict[int, int]:
        """The same for every prefix of a long pre-token, in one forward run."""
        last, fits, beside = {}, self.fits, self._beside
        for at, (token, length) in self.automaton.iter(raw):
            end = at + 1
            if end in last:
                continue
            start = end - length
            if start:
                fit = fits.get(last[start] << 24 | token)
                if not (beside(last[start], token) if fit is None else fit):
                    continue
            last[end] = token
        return last

    def split(self, text: str) -> list[str]:
        """Pre-tokens of a text, as the library splits it.

        The regex module knows letters and digits of later Unicode versions,
        which the library takes for signs; texts that hold such a code point
        go by a pattern without them.
        """
        if text.isascii() or max(text) < chr(_NEAR):
            return self.find_near(text)
        if self.find_new is None:
            late = later_letters(self.path)
            apart = SPLIT if not late else SPLIT.replace(r"\p{L}+", f"[\\p{{L}}--[{late}]]+", 1).replace(r"\p{N}+", f"[\\p{{N}}--[{late}]]+", 1)
            apart = apart if not late else apart.replace(r"[^\s\p{L}\p{N}]+", f"[[^\\s\\p{{L}}\\p{{N}}]||[{late}]]+")
            self.find_new = regex.compile(f"[{late}]" if late else r"(?!)").search, regex.compile(apart, regex.V1).findall
        return (self.find_new[1] if self.find_new[0](text) else self.find)(text)

    def encode(self, text: str) -> bytes:
        """Ids of a whole text as little-endian unsigned 32-bit integers."""
        words = self.words.__getitem__
        if self.apart is None or not any(s in text for s in self.special):
            return b"".join(map(words, self.split(text)))
        return b"".join(
            np.uint32(self.special[part]).astype("<u4").tobytes() if part in self.special else b"".join(map(words, self.split(part)))
            for part in self.apart.split(text) if part
        )

    def decode(self, ids: bytes) -> str:
        return b"".join(map(self.text.__getitem__, np.frombuffer(ids, "<u4").tolist())).decode("utf-8", "replace")


def later_letters(path: str) -> str:
    """Letters and digits of the regex module that the library takes for signs, as the inside of a class."""
    pieces = Tokenizer.from_file(path).pre_tokenizer.pre_tokenize_str
    new = (chr(c) for c in range(sys.maxunicode + 1) if not 0xD800 <= c < 0xE000 and unicodedata.category(chr(c)) == "Cn")
    found = [ord(c) for c in regex.findall(r"[\p{L}\p{N}]", "".join(new)) if len(pieces("a" + c)) > 1 and len(pieces("1" + c)) > 1]
    starts = [c for i, c in enumerate(found) if i == 0 or found[i - 1] != c - 1]
    ends = [c for i, c in enumerate(found) if i + 1 == len(found) or found[i + 1] != c + 1]
    return "".join(f"\\U{a:08x}-\\U{b:08x}" for a, b in zip(starts, ends, strict=True))


@lru_cache(maxsize=2)
def codec(path: str) -> Bpe:
    return Bpe(path)


@lru_cache(maxsize=2)
def _ranked(path: str):
    """The same vocabulary as a file of ranks, in the library that counts quickest."""
    with open(path, "rb") as f:
        ranks = {base64.b64decode(token): int(rank) for token, rank in map(bytes.split, f)}
    return tiktoken.Encoding("ranks", pat_str=SPLIT, mergeable_ranks=ranks, special_tokens={"<|endoftext|>": len(ranks)})


def lengths(docs: DataFrame, ranks: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, length) of each text: its tokens plus one for the mark at its end (null texts: that one). Narrow.

    Only counts are asked for here, so they come from the library, by the file
    of ranks of the vocabulary.
    """
    def run(batches):
        count = _ranked(ranks).encode
        for batch in batches:
            n = [len(count(t.as_py() or "", allowed_special="all")) + 1 for t in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n, pa.int64())], ["id", "length"])

    slim = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    return slim.mapInArrow(run, f"id {dict(slim.dtypes)['id']}, length long").withColumnRenamed("id", id_col)


def encode_decode(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text", digests: bool = False) -> DataFrame:
    """Encode and decode each text: (id, n_tokens, ids, decoded) or digests.

    One row per input row; a null text counts as empty (0 tokens). With
    ``digests`` the ids and the decoded text stay in the worker and only their
    SHA-256 leave it. Narrow: no shuffle, one bounded codec per worker.
    """
    rest = "ids_sha256 string, decoded_sha256 string" if digests else "ids array<int>, decoded string"

    def run(batches):
        bpe = codec(path)
        for batch in batches:
            n, ids_out, texts_out = [], [], []
            for text in batch.column(1):
                ids = bpe.encode(text.as_py() or "")
                decoded = bpe.decode(ids)
                n.append(len(ids) // 4)
                ids_out.append(hashlib.sha256(ids).hexdigest() if digests else np.frombuffer(ids, "<i4"))
                texts_out.append(hashlib.sha256(decoded.encode()).hexdigest() if digests else decoded)
            kinds = (pa.string(), pa.string()) if digests else (pa.list_(pa.int32()), pa.string())
            names = ["id", "n_tokens", *(x.split()[0] for x in rest.split(", "))]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n, pa.int64()), pa.array(ids_out, kinds[0]), pa.array(texts_out, kinds[1])], names)

    slim = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text"))
    return slim.mapInArrow(run, f"id long, n_tokens long, {rest}").withColumnRenamed("id", id_col)
