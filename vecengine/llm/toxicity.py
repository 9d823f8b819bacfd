"""Toxicity by class-conditional Kneser-Ney language models.

Two interpolated Kneser-Ney bigram models, one of toxic and one of ordinary
labelled text, share the lowest level: the continuation counts of both classes
together. A text's log-likelihood ratio is normalised by length, over the whole
text and over its windows, and calibrated.

Whether an expression may speak for itself is a matter of evidence: of its
counts by class, the log-likelihood statistic against the classes' shares must
reach a bound. Below it both classes take the shared backoff counts and the
ratio of that level is 0. All counts are gathered and stay a table; the ratios
that have evidence are what scoring needs.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecengine.llm.calibrate import CALIBRATION_ROWS, Logistic, fold, held_out, labelled, sampled
from vecengine.llm.common import small_batches, staged

WORDS = re.compile(r"[^\W\d_]+").findall
DISCOUNT, WINDOW = 0.75, 12
#: Rows of a block, as a power of two: a block's n-grams are looked up together, each once.
BLOCK_BITS = 9
#: The history of a text's first word, and what tells a history's key from the word's.
START, HISTORY = -0x61C8864680B583EB, 0x2545F4914F6CDD1D
#: A bigram's key is the history's hash, turned by so many bits, xor the word's.
TURN = 23
#: Bounds of a word's evidence from which the calibration fold chooses, and the bound for bigrams and
#: histories: there are millions of bigrams, so chance alone brings many to a low one.
EVIDENCE, PAIR_EVIDENCE = (4.0, 6.0, 10.0, 16.0), 25.0
#: Features of a text at each of the two levels.
LEVEL = 5
#: Ratios (16 bytes each) up to which every worker gets all of them; beyond, texts and ratios meet by a join.
BROADCAST_RATIOS = 8_000_000
_MEMO = 100_000
#: Texts whose n-grams are looked up at a time.
_SLICE = 200
_PAIR, _WORD, _HISTORY = 0, 1, 2


class _Hashes(dict):
    """Word to its 64-bit hash; bounded."""

    def __missing__(self, word: str) -> int:
        if len(self) >= _MEMO:
            self.clear()
        out = self[word] = xxhash.xxh3_64_intdigest(word) - (1 << 63)
        return out


def _hashed(memo: _Hashes, text: str | None) -> np.ndarray:
    words = WORDS((text or "").lower())
    return np.fromiter(map(memo.__getitem__, words), np.int64, len(words))


def _ngrams(texts: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(history, word, bigram key) of all words of the texts, one after the other."""
    w = np.concatenate([np.empty(0, np.int64), *texts])
    h = np.concatenate(([START], w[:-1])) if len(w) else w
    begins = np.cumsum([0, *map(len, texts)])[:-1]
    h[begins[begins < len(w)]] = START
    turned = h.view(np.uint64)
    turned = turned << np.uint64(TURN) | turned >> np.uint64(64 - TURN)
    return h, w, (turned ^ w.view(np.uint64)).view(np.int64)


def _bigram_counts(batches):
    """(history, word, times by class) summed per batch."""
    memo = _Hashes()
    for batch in batches:
        texts = [_hashed(memo, t.as_py()) for t in batch.column(0)]
        h, w, k = _ngrams(texts)
        k, at, which = np.unique(k, return_index=True, return_inverse=True)
        ones = np.bincount(which, np.repeat(batch.column(1).to_numpy() > 0, list(map(len, texts))), len(k)).astype(np.int64)
        yield pa.RecordBatch.from_arrays([pa.array(x) for x in (h[at], w[at], np.bincount(which, minlength=len(k)) - ones, ones)], ["h", "w", "n0", "n1"])


def _block_keys(batches):
    """(block, key) of the distinct words, histories and bigrams of each block."""
    memo = _Hashes()
    for batch in batches:
        blocks = batch.column(0).to_numpy()
        for block in np.unique(blocks):
            h, w, k = _ngrams([_hashed(memo, batch.column(1)[int(i)].as_py()) for i in np.flatnonzero(blocks == block)])
            keys = np.concatenate((np.unique(w), np.unique(h) ^ HISTORY, np.unique(k)))
            for at in range(0, len(keys), 100_000):
                part = keys[at : at + 100_000]
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(part), block)), pa.array(part)], ["__block", "__key"])


@dataclass
class Model:
    #: (key, ratio, evidence), keys unique: the log ratio of a word, a history's backoff weight, or a bigram.
    ratios: DataFrame
    #: Evidence below which a word takes the shared counts, so adds nothing.
    evidence: float = EVIDENCE[0]
    calibrator: Logistic | None = None
    #: The same as sorted arrays, if they are few enough to go to every worker.
    sent: object = None


def evidence(a, b, share: float):
    """Twice the log-likelihood ratio of counts ``a`` (ordinary) and ``b`` (toxic) against the toxic share; 0 for a class without any text."""
    if not 0 < share < 1:
        return F.lit(0.0)
    n = (a + b).cast("double")
    part = lambda x, p: F.when(x > 0, x * F.log(x / (n * p))).otherwise(0.0)
    return 2 * (part(a.cast("double"), 1 - share) + part(b.cast("double"), share))


def counts(train: DataFrame, share: float, least: float = PAIR_EVIDENCE) -> DataFrame:
    """(kind, key, a, b, c, d, e, h, w) of every word and history of ``train(text, y)``, and of the bigrams with evidence.

    a and b: times by class; c and d: distinct histories of a word (followers
    of a history) by class, e: of both together. All bigrams are summed in one
    shuffle; what goes on from there are partial sums.
    """
    grams = train.mapInArrow(_bigram_counts, "h long, w long, n0 long, n1 long").groupBy("h", "w").agg(F.sum("n0").alias("a"), F.sum("n1").alias("b"))
    none = F.lit(None).cast("long")
    row = lambda kind, key, h=none, w=none: F.struct(F.lit(kind).alias("kind"), key.alias("key"), h.alias("h"), w.alias("w"))
    turned = F.shiftleft("h", TURN).bitwiseOR(F.shiftrightunsigned("h", 64 - TURN))
    own = [row(_WORD, F.col("w")), row(_HISTORY, F.col("h").bitwiseXOR(F.lit(HISTORY)))]
    pair = row(_PAIR, turned.bitwiseXOR(F.col("w")), F.col("h"), F.col("w"))
    each = grams.select(F.explode(F.when(evidence(F.col("a"), F.col("b"), share) >= least, F.array(*own, pair)).otherwise(F.array(*own))).alias("g"), "a", "b")
    positive = lambda c: F.sum((F.col(c) > 0).cast("long"))
    return each.groupBy("g.kind", "g.key").agg(F.sum("a").alias("a"), F.sum("b").alias("b"), positive("a").alias("c"), positive("b").alias("d"), F.count("*").alias("e"), F.max("g.h").alias("h"), F.max("g.w").alias("w"))


def fit(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label: str = "toxic") -> Model:
    """Fit on the labelled rows of the folds 1 to 4 (fold: crc32(id) mod 5).

    Counts cover every word, history and bigram of the labelled rows of folds 1
    to 3 and grow with the corpus; the driver gets sums, and the ratios that
    have evidence while they are few. Fold 4 (at most CALIBRATION_ROWS rows)
    calibrates and chooses the bound of the evidence.
    """
    spark = docs.sparkSession
    small_batches(spark)
    train = labelled(docs, labels, label, fold(1, 2, 3), id_col, text_col).select("text", "y")
    least = EVIDENCE[0]
    size = train.groupBy((F.col("y") > 0).cast("int").alias("y")).agg(F.sum(F.octet_length("text"))).collect()
    text = dict((r[0], float(r[1] or 0)) for r in size)
    share = text.get(1, 0.0) / max(1.0, sum(text.values()))
    sums = staged(counts(train, share), "kn-counts")
    total = sums.where(F.col("kind") == _WORD).agg(*(F.coalesce(F.sum(c), F.lit(0)) for c in "cde"), *(F.count(F.when(F.col(c) > 0, 1)) for c in "cd"), F.count("*")).first()
    follow, bigrams, kinds, words = total[:2], total[2], total[3:5], total[5]
    spread = follow[1] / max(1, sum(follow))
    smooth = lambda y, n: (F.greatest(F.col(f"{n}_{'cd'[y]}") - DISCOUNT, F.lit(0.0)) + DISCOUNT * kinds[y] * (F.col(f"{n}_e") + 0.5) / (bigrams + 0.5 * (words + 1))) / max(1, follow[y])
    back = lambda y, n: F.when(F.col(f"{n}_{'ab'[y]}") > 0, DISCOUNT * F.col(f"{n}_{'cd'[y]}") / F.col(f"{n}_{'ab'[y]}")).otherwise(1.0)
    named = lambda df, n: df.select(F.col("key").alias(f"{n}_key"), *(F.col(c).alias(f"{n}_{c}") for c in "abcde"))
    word, history = named(sums.where(F.col("kind") == _WORD), "w"), named(sums.where(F.col("kind") == _HISTORY), "h")
    rare, backed = F.log(smooth(1, "w")) - F.log(smooth(0, "w")), F.log(back(1, "h")) - F.log(back(0, "h"))
    pairs = sums.where(F.col("kind") == _PAIR).select("key", "h", "w", F.col("a").alias("n0"), F.col("b").alias("n1"), evidence(F.col("a"), F.col("b"), share).alias("evidence"))
    met = pairs.join(word, F.col("w") == F.col("w_key")).join(history, F.col("h").bitwiseXOR(F.lit(HISTORY)) == F.col("h_key"))
    seen = lambda y: F.log(F.greatest(F.col(f"n{y}") - DISCOUNT, F.lit(0.0)) / F.greatest(F.col(f"h_{'ab'[y]}"), F.lit(1)) + back(y, "h") * smooth(y, "w"))
    # A bigram with evidence stands for itself, interpolated with what its history leaves to the words.
    ratios = met.select("key", (seen(1) - seen(0)).alias("ratio"), F.greatest("evidence", F.lit(least)).alias("evidence"))
    for df, n, ratio, bound in ((word, "w", rare, least), (history, "h", backed, PAIR_EVIDENCE)):
        own = df.select(F.col(f"{n}_key").alias("key"), ratio.alias("ratio"), evidence(F.col(f"{n}_c"), F.col(f"{n}_d"), spread).alias("evidence"))
        ratios = ratios.union(own.where(F.col("evidence") >= bound))
    ratios = staged(ratios.groupBy("key").agg(F.max_by("ratio", "evidence").alias("ratio"), F.max("evidence").alias("evidence")), "kn-ratios")
    model = Model(ratios)
    if ratios.count() <= BROADCAST_RATIOS:
        got = ratios.toPandas().sort_values("key")
        model.sent = spark.sparkContext.broadcast((got["key"].to_numpy(np.int64), got["ratio"].to_numpy(np.float32), got["evidence"].to_numpy(np.float32)))
    sample = staged(sampled(docs, labels, label, fold(4), CALIBRATION_ROWS, id_col=id_col, text_col=text_col).select("y", F.col("text").alias("__text")), "kn-sample")
    extra = ", ".join(f"x{i} double" for i in range(2 * LEVEL * len(EVIDENCE)))
    got = _featured(sample, model, 1, 1, extra, lambda found: [pa.array(x) for x in found.T], EVIDENCE).toPandas()
    y, best = got["y"].to_numpy(), np.inf
    for i, bound in enumerate(EVIDENCE):
        x = got[[f"x{j}" for j in range(2 * LEVEL * i, 2 * LEVEL * (i + 1))]].to_numpy()
        tried = Logistic(x, y)
        p = np.clip(tried(x), 1e-12, 1 - 1e-12)
        loss = float(-np.log(np.where(y > 0, p, 1 - p)).mean()) if len(y) else 0.0
        if loss < best:
            best, model.evidence, model.calibrator = loss, bound, tried
    return model


class _Ratios:
    """Log ratios of the words of texts."""

    def __init__(self, keys: np.ndarray, ratios: np.ndarray, had: np.ndarray):
        self.keys, self.ratios, self.had = keys, np.append(ratios, 0.0).astype(np.float64), np.append(had, 0.0)

    def _of(self, keys: np.ndarray) -> np.ndarray:
        """Place of each key; that of a ratio of 0 without evidence for unknown ones."""
        if not len(self.keys):
            return np.zeros(len(keys), np.int64)
        at = np.minimum(np.searchsorted(self.keys, keys), len(self.keys) - 1)
        return np.where(self.keys[at] == keys, at, len(self.keys))

    def levels(self, h: np.ndarray, w: np.ndarray, k: np.ndarray, bounds):
        """For each bound of the evidence: the ratios of the words alone, and those of the bigrams that have evidence, backing off to the words."""
        word, history, pair = self._of(w), self._of(h ^ HISTORY), self._of(k)
        for bound in bounds:
            alone = np.where(self.had[word] >= bound, self.ratios[word], 0.0)
            yield alone, np.where(self.had[pair] > 0, self.ratios[pair], alone + self.ratios[history])


def _features(ratio: np.ndarray) -> tuple[float, ...]:
    """Mean log ratio, the best window's mean, the best word's, the three best words' mean, and what speaks for toxicity over the root of the length."""
    if not len(ratio):
        return (0.0,) * LEVEL
    sums = np.concatenate(([0.0], np.cumsum(ratio)))
    size = min(WINDOW, len(ratio))
    best = np.sort(ratio)[-3:] if len(ratio) <= 3 else np.partition(ratio, len(ratio) - 3)[-3:]
    window = (sums[size:] - sums[:-size]).max() / size
    return float(ratio.mean()), float(window), float(best.max()), float(best.mean()), float(np.maximum(ratio, 0).sum() / np.sqrt(len(ratio)))


def _all_features(texts: list[np.ndarray], keys: np.ndarray, ratios: np.ndarray, had: np.ndarray, bounds) -> np.ndarray:
    """(texts, 2 LEVEL for each bound of the evidence)."""
    grams, ends, columns = _ngrams(texts), np.cumsum(list(map(len, texts)))[:-1], []
    for both in _Ratios(keys, ratios, had).levels(*grams, bounds):
        columns += [np.array([_features(r) for r in (np.split(ratio, ends) if texts else [])]).reshape(-1, LEVEL) for ratio in both]
    return np.hstack(columns)


def _featured(rows: DataFrame, model: Model, width: int, at: int, extra: str, finish, bounds: tuple[float, ...] | None = None) -> DataFrame:
    """The first ``width`` columns and what ``finish`` makes of the features of column ``at``.

    Narrow if every worker has the ratios, else block by block.
    """
    bounds = bounds or (model.evidence,)
    names = [*rows.columns[:width], *(x.split()[0].strip("`") for x in extra.split(", "))]
    kinds = ", ".join(f"`{n}` {t}" for n, t in rows.dtypes[:width])
    if model.sent is None:
        return _by_block(rows, model, width, at, f"{kinds}, {extra}", names, finish, bounds)
    sent = model.sent

    def run(batches):
        memo, known = _Hashes(), sent.value
        for whole in batches:
            for start in range(0, whole.num_rows, _SLICE):
                batch = whole.slice(start, _SLICE)
                found = _all_features([_hashed(memo, t.as_py()) for t in batch.column(at)], *known, bounds)
                yield pa.RecordBatch.from_arrays([*(batch.column(i) for i in range(width)), *finish(found)], names)

    return rows.mapInArrow(run, f"{kinds}, {extra}")


def _by_block(rows: DataFrame, model: Model, width: int, at: int, schema: str, names: list[str], finish, bounds) -> DataFrame:
    """The same for more ratios than a worker should hold.

    Rows are written in blocks; a block's distinct n-grams are joined with the
    ratios, so a word's rows are at most one a block and batch, and what was
    found meets the block's texts. A task holds one block and its n-grams.
    """
    blocks = staged(rows.withColumn("__block", F.shiftright(F.monotonically_increasing_id(), BLOCK_BITS)), "kn-blocks")
    keys = blocks.select("__block", blocks.columns[at]).mapInArrow(_block_keys, "__block long, __key long")
    found = keys.join(model.ratios, F.col("__key") == F.col("key")).select("__block", "key", "ratio", "evidence")

    def run(mine: pa.Table, seen: pa.Table) -> pa.Table:
        memo = _Hashes()
        known, first = np.unique(seen.column("key").to_numpy(), return_index=True)
        ratios, had = (seen.column(c).to_numpy()[first].astype(np.float32) for c in ("ratio", "evidence"))
        features = _all_features([_hashed(memo, t.as_py()) for t in mine.column(at)], known, ratios, had, bounds)
        return pa.Table.from_arrays([*(mine.column(i) for i in range(width)), *finish(features)], names)

    return blocks.groupBy("__block").cogroup(found.groupBy("__block")).applyInArrow(run, schema)


def score(docs: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text", keep: tuple[str, ...] = (), out: str = "score") -> DataFrame:
    """(id, *keep, score) of every whole text, one row per input row.

    Null and empty texts have ratio 0. With labels of one class only, every
    score is that class; without labels it is 0.
    """
    small_batches(docs.sparkSession)
    # A text that is kept anyway goes to Python once.
    kept = text_col in keep and dict(docs.dtypes)[text_col] == "string"
    slim = docs.select(F.col(id_col), *keep) if kept else docs.select(F.col(id_col), *keep, F.col(text_col).cast("string").alias("__text"))
    width = len(keep) + 1
    at = 1 + keep.index(text_col) if kept else width
    calibrator = model.calibrator
    return _featured(slim, model, width, at, f"`{out}` double", lambda found: [pa.array(calibrator(found))])


def classify(docs: DataFrame, labels: DataFrame, threshold: float = 0.5) -> DataFrame:
    """(doc_id, held_out, score, predicted) of all documents."""
    model = fit(docs, labels)
    scored = score(docs.select("doc_id", held_out().alias("held_out"), "text"), model, keep=("held_out",))
    return scored.withColumn("predicted", (F.col("score") >= threshold).cast("int"))
