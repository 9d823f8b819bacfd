import zlib
from collections import Counter

import numpy as np
import public_tokenizers
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from vecengine.llm import bpe, calibrate, language_id, ngram_join, packing, quality, token_counts, toxicity

PATH = public_tokenizers.path("byte_bpe_50k.json")
LIB = Tokenizer.from_file(PATH)
ODD = [None, "", " ", "\n\n", "a", "The cat's 12 hats, we'll see  now", "<|endoftext|>x", "é漢🙂" * 50, "a" * 5000, "x " * 3000]


def docs(spark, texts, extra=False):
    cols = "doc_id long, text string" + (", score double, n string, part string" if extra else "")
    return spark.createDataFrame([(i, t, *((0.5, "n", "p") if extra else ())) for i, t in enumerate(texts)], cols)


@settings(max_examples=200, deadline=None)
@given(st.text(max_size=40) | st.text(alphabet="ab 'lsve\n1é", max_size=60))
def test_encoding_equals_the_library_and_comes_back(text):
    codec = bpe.codec(PATH)
    ids = codec.encode(text)
    assert np.frombuffer(ids, "<u4").tolist() == LIB.encode(text, add_special_tokens=False).ids
    assert codec.decode(ids) == LIB.decode(np.frombuffer(ids, "<u4").tolist(), skip_special_tokens=False)


def test_encode_decode_of_odd_rows(spark):
    out = {r["doc_id"]: r for r in bpe.encode_decode(docs(spark, ODD, True), PATH).collect()}
    assert len(out) == len(ODD) and all(out[i]["decoded"] == (t or "") for i, t in enumerate(ODD))
    assert bpe.encode_decode(docs(spark, []), PATH).count() == 0


@settings(max_examples=150, deadline=None)
@given(st.text(alphabet="ab 'lsve\n1é,", max_size=300), st.lists(st.tuples(st.integers(0, 320), st.integers(0, 30), st.text(alphabet="l ' a\n", max_size=6)), max_size=4))
def test_edited_counts_equal_counts_afresh(text, edits):
    codec = bpe.codec(PATH)
    chars, tokens, _ = token_counts.leaves_of(text, codec)
    tree = token_counts.TokenTree(text, codec, chars, tokens)
    for e in edits:
        tree.edit(*e)
    after = token_counts._afresh(text, edits)
    assert tree.text == after and tree.n_tokens == len(codec.encode(after)) // 4
    # What is stored carries on: an edit of the edited tree counts right too.
    again = token_counts.TokenTree(after, codec, *map(np.array, tree.stored()))
    again.edit(len(after) // 2, 2, " x'll")
    assert again.n_tokens == len(codec.encode(again.text)) // 4


def test_edits_touch_little_of_a_long_text():
    text = "one two three four " * 5000
    chars, tokens, _ = token_counts.leaves_of(text, bpe.codec(PATH))
    tree = token_counts.TokenTree(text, bpe.codec(PATH), chars, tokens)
    leaves = len(tree.leaves)
    tree.edit(40_000, 3, "xyz")
    # The touched leaf and one at its border; all other leaves stay unread.
    assert 0 < tree.encoded < 3 * token_counts.LEAF and len(tree.leaves) == leaves
    assert sum(not isinstance(x, int) for x in tree.leaves) <= 3


def test_count_tokens_of_odd_rows_and_edits(spark):
    edits = [[(0, 1, "z")], None, [], [(3, 500, None), (None, None, "new ")], [(1, 0, "<|endoftext|>")]]
    rows = [(i, t, e, "x") for i, (t, e) in enumerate((t, e) for t in ODD for e in edits)]
    d = spark.createDataFrame(rows, "doc_id long, text string, edits array<struct<at:int,del:int,ins:string>>, n_tokens string")
    got = token_counts.count_tokens(d, PATH, "edits").collect()
    size = lambda t: len(LIB.encode(t, add_special_tokens=False).ids)
    assert len(got) == len(rows)
    for r in got:
        _, text, e, _ = rows[r["doc_id"]]
        after = token_counts._afresh(text or "", [(a or 0, b or 0, c or "") for a, b, c in e or []])
        assert (r["n_chars"], r["n_tokens"], r["n_tokens_after"]) == (len(text or ""), size(text or ""), size(after)), r
    assert token_counts.count_tokens(d.where("false"), PATH, "edits").count() == 0
    plain = token_counts.count_tokens(d, PATH).collect()
    assert len(plain) == len(rows) and all(r["n_tokens"] == r["n_tokens_after"] for r in plain)


def test_stored_trees_take_later_edits(spark):
    d = docs(spark, ["The cat's 12 hats, we'll see  now " * 40, None])
    trees = token_counts.grow(d, PATH)
    for place in (5, 300):
        trees = token_counts.edit(trees.withColumn("e", F.expr(f"array(struct({place} AS at, 7 AS del, '!! ' AS ins))")), PATH, "e")
    for r in trees.collect():
        assert r["n_tokens"] == sum(r["leaf_tokens"]) == len(LIB.encode(r["text"]).ids) and r["n_chars"] == sum(r["leaf_chars"]) == len(r["text"])


def test_languages_ties_and_texts_without_letters(spark):
    train = spark.createDataFrame([("the cat and the dog of the house", "en"), ("der hund und die katze im haus", "de"), (None, "en"), ("x", None)], "text string, lang string")
    known = language_id.profiles(train)
    got = [r["lang_pred"] for r in language_id.identify(docs(spark, ["the house and the cat", "die katze und der hund", "123 !!", None, ""]), known).orderBy("doc_id").collect()]
    assert got == ["en", "de", "und", "und", "und"]
    assert language_id.identify(docs(spark, ["abc"]), {}).first()["lang_pred"] == "und"


def by_brute_force(texts, langs, held, size):
    """Predictions by strings and dictionaries."""
    def grams(text):
        t = " " + " ".join("".join(c if c.isalpha() else " " for c in (text or "").lower()).split()) + " "
        return Counter(g for k in (1, 2, 3) for i in range(len(t) - k + 1) if (g := t[i : i + k]) != " ") if t.strip() else Counter()

    top = lambda c: {g: i for i, (g, _) in enumerate(sorted(c.items(), key=lambda x: (-x[1], len(x[0]), x[0]))[:size])}
    sums: dict[str, Counter] = {}
    for t, lang, h in zip(texts, langs, held, strict=True):
        if lang and not h:
            sums.setdefault(lang, Counter()).update(grams(t))
    known = {k: top(v) for k, v in sums.items()}
    out = []
    for t in texts:
        mine = top(grams(t))
        out.append(min(known, key=lambda k: (sum(abs(known[k][g] - i) if g in known[k] else size for g, i in mine.items()), k)) if mine else "und")
    return out


def test_languages_equal_brute_force_in_any_script(spark):
    rng = np.random.default_rng(8)
    words = {"el": "η ΓΆΤΑ και ο σκύλος στο σπίτι", "ru": "КОШКА и собака в доме у реки", "en": "the Cat and a dog in the house", "zh": "猫 和 狗 在 河边 的 房子"}
    texts, langs = [], []
    for i in range(80):
        lang = sorted(words)[i % 4]
        texts.append(" ".join(rng.choice(words[lang].split(), 12)).swapcase() if i % 3 else " ".join(rng.choice(words[lang].split(), 5)))
        langs.append(None if i % 11 == 0 else lang)
    texts, langs = [*texts, "", None, "12 3!", "x" * 30_000], [*langs, "en", "ru", None, "en"]
    held = [i % 4 == 2 for i in range(len(texts))]
    d = spark.createDataFrame([(i, t, g, h, "p") for i, (t, g, h) in enumerate(zip(texts, langs, held, strict=True))], "doc_id long, text string, lang string, held boolean, score string")
    for size in (40, 400):
        known = language_id.profiles(d.where("not held"), size=size)
        got = [r["lang_pred"] for r in language_id.identify(d, known, size=size, keep=("held",)).orderBy("doc_id").collect()]
        assert got == by_brute_force(texts, langs, held, size)
    assert language_id.identify(d.where("false"), known).count() == 0 and language_id.profiles(d.where("false")) == {}
    twice = language_id.identify(d.union(d), known)
    assert twice.count() == 2 * len(texts) == 2 * twice.distinct().count()


def cheapest(lengths, sizes):
    """The least cost over all ways to share the pieces out."""
    full = (1 << len(lengths)) - 1
    used = [sum(n for i, n in enumerate(lengths) if m >> i & 1) for m in range(full + 1)]
    best = [0.0] + [float("inf")] * full
    for m in range(1, full + 1):
        s = m
        while s:
            if s & m & -m and used[s] <= sizes[-1]:
                best[m] = min(best[m], packing.cost(next(c for c in sizes if c >= used[s])) + best[m ^ s])
            s = (s - 1) & m
    return best[full]


def test_packing_is_near_the_optimum():
    rng = np.random.default_rng(3)
    ratios = []
    for _ in range(60):
        lengths = [int(rng.choice([rng.integers(1, 600), rng.integers(1, 3000), rng.integers(4000, 8193)])) for _ in range(rng.integers(1, 8))]
        bins = {b: c for b, c, _ in packing.pack(lengths)}
        ratios.append(sum(map(packing.cost, bins.values())) / cheapest(lengths, packing.CAPACITIES))
    assert max(ratios) < 1.1 and np.mean(ratios) < 1.01
    # Short pieces alone do not open long bins; ties go by place.
    assert max(c for _, c, _ in packing.pack([500] * 16)) <= 1024
    assert packing.pack([5, 5, 5], (8, 16)) == packing.pack([5, 5, 5], (8, 16))
    assert packing.pack([]) == []


def test_bins_of_many_tasks_are_packed_again(spark):
    d = spark.range(0, 400, 1, 100).selectExpr("id AS doc_id", "100 AS n", "'x' AS bin")
    out = packing.best_fit(d, length_col="n").toPandas()
    caps = out.drop_duplicates("bin").capacity
    assert len(out) == 400 and out.doc_id.nunique() == 400 and out.length.sum() / caps.sum() > 0.95
    assert packing.best_fit(d.where("false"), length_col="n").count() == 0
    assert packing.best_fit(d.union(d), length_col="n").count() == 800


def test_packing_fits_and_downsizes(spark):
    rng = np.random.default_rng(1)
    lengths = rng.integers(1, 60, 500).tolist()
    put = packing.pack(lengths, (16, 32, 64))
    used: dict[int, int] = {}
    for n, (b, c, at) in zip(lengths, put, strict=True):
        assert at + n <= c
        used[b] = used.get(b, 0) + n
    caps = {b: c for b, c, _ in put}
    assert all(c == min(s for s in (16, 32, 64) if s >= used[b]) for b, c in caps.items())
    assert sum(used.values()) / sum(caps.values()) > 0.95
    out = packing.best_fit(docs(spark, [*ODD, "w " * 40_000], True)).toPandas()
    assert out[out.doc_id == len(ODD)]["length"].sum() == 40_001 and out.doc_id.nunique() == len(ODD) + 1
    spans = out.sort_values(["bin", "offset"])
    assert all((g.offset.to_numpy()[1:] == (g.offset + g.length).to_numpy()[:-1]).all() for _, g in spans.groupby("bin"))


def test_packing_counts_tokens(spark, tmp_path):
    from vecengine.llm import registry

    texts = [*ODD, "漢字" * 9000]
    docs(spark, texts).write.parquet(f"{tmp_path}/documents.parquet")
    out = registry.op10_best_fit_packing(spark, str(tmp_path)).toPandas()
    want = {i: len(LIB.encode(t or "").ids) + 1 for i, t in enumerate(texts)}
    assert out.groupby("doc_id").length.sum().to_dict() == want and (out.offset + out.length <= out.capacity).all()


def labelled(spark, n, word, label):
    rng = np.random.default_rng(5)
    rows, marks = [], []
    for i in range(n):
        bad = i % 3 == 0
        words = rng.choice(["sun", "moon", "tree", "river", "stone", "bird", "wind", "cloud"], 30).tolist()
        rows.append((i, " ".join(words + [word] * (3 if bad else 0)) if label == "toxic" else " ".join(w.upper() + "!!" if bad else w for w in words)))
        marks.append((i, int(bad) if label == "toxic" else int(not bad)))
    return spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame(marks, f"doc_id long, {label} int")


@pytest.mark.parametrize(("module", "label"), [(toxicity, "toxic"), (quality, "quality")])
def test_classifiers_on_held_out_rows(spark, module, label):
    d, marks = labelled(spark, 300, "vile", label)
    got = module.classify(d, marks).toPandas()
    want = marks.toPandas().set_index("doc_id")[label]
    held = got[got.held_out]
    assert set(held.doc_id) == {i for i in range(300) if zlib.crc32(str(i).encode()) % 5 == 0}
    assert (held.predicted == held.doc_id.map(want)).mean() > 0.95 and got.score.between(0, 1).all()


def test_toxicity_counts_words_of_few_texts(spark):
    # Each bad word and each other rare word is in four texts at most, so in fewer than five training texts.
    d, marks = labelled(spark, 300, "", "toxic")
    letters = str.maketrans("0123456789", "abcdefghij")
    rare = [(r.doc_id, f"{r.text} " + f"{'z' if r.doc_id % 3 else 'q'}{r.doc_id % (75 if r.doc_id % 3 == 0 else 74)} ".translate(letters) * 3) for r in d.collect()]
    rare = spark.createDataFrame(rare, "doc_id long, text string")
    got = toxicity.classify(rare, marks).toPandas()
    want = marks.toPandas().set_index("doc_id")["toxic"]
    held = got[got.held_out]
    assert (held.predicted == held.doc_id.map(want)).mean() > 0.85


def test_toxicity_model_grows_with_its_words(spark):
    letters = str.maketrans("0123456789", "abcdefghij")
    texts = [" ".join(f"w{i * 150 + j}".translate(letters) for j in range(150)) for i in range(600)]
    trained = [i for i in range(600) if zlib.crc32(str(i).encode()) % 5 in (1, 2, 3)]
    rows = spark.createDataFrame([(texts[i], i % 2) for i in trained], "text string, y int")
    found = toxicity.counts(rows, 0.5).toPandas()
    words = found[found.kind == toxicity._WORD]
    assert len(words) == 150 * len(trained) > 1 << 15 and (words.a + words.b == 1).all() and (words.e == 1).all()


def test_counts_equal_brute_force(spark):
    texts = [("b a b a", 1), ("a b", 0), ("", 0), (None, 1), ("b a", 1)]
    found = toxicity.counts(spark.createDataFrame(texts, "text string, y int"), 0.5, -1.0).toPandas()
    pairs: Counter = Counter()
    for t, y in texts:
        w = [None, *(t or "").split()]
        pairs.update((h, x, y) for h, x in zip(w, w[1:], strict=False))
    for kind, at in ((toxicity._WORD, 1), (toxicity._HISTORY, 0)):
        want = []
        for k in {p[at] for p in pairs}:
            own = {p: n for p, n in pairs.items() if p[at] == k}
            want.append((*(sum(n for p, n in own.items() if p[2] == y) for y in (0, 1)), *(len({p[1 - at] for p in own if p[2] == y}) for y in (0, 1)), len({p[1 - at] for p in own})))
        assert sorted(found[found.kind == kind][list("abcde")].itertuples(index=False, name=None)) == sorted(want)
    assert (found.kind == toxicity._PAIR).sum() == len({p[:2] for p in pairs})


def test_scores_do_not_depend_on_the_way_that_ratios_and_labels_travel(spark, monkeypatch):
    d, marks = labelled(spark, 300, "vile", "toxic")
    d = d.union(spark.createDataFrame([(900, None), (901, ""), (902, "vile " * 5000), (902, "sun")], d.schema))
    one = toxicity.classify(d, marks).toPandas().sort_values(["doc_id", "score"])
    monkeypatch.setattr(toxicity, "BROADCAST_RATIOS", -1)
    monkeypatch.setattr(calibrate, "BROADCAST_ROWS", -1)
    two = toxicity.classify(d, marks).toPandas().sort_values(["doc_id", "score"])
    assert np.allclose(one.score, two.score) and (one.predicted.to_numpy() == two.predicted.to_numpy()).all() and len(one) == 304


@pytest.mark.parametrize("module", [toxicity, quality])
def test_conflicting_labels_and_repeated_rows(spark, module):
    label = "toxic" if module is toxicity else "quality"
    d, marks = labelled(spark, 200, "vile", label)
    more = marks.union(marks.selectExpr("doc_id", f"0 AS {label}")).union(spark.createDataFrame([(None, 1), (5, None)], marks.schema))
    one, two = (module.classify(d.union(d), m).toPandas().drop_duplicates().sort_values("doc_id") for m in (marks, more))
    assert len(one) == 200 and np.allclose(one.score, two.score)
    assert module.classify(d.where("false"), marks).count() == 0


@pytest.mark.parametrize("module", [toxicity, quality])
def test_classifiers_without_labels_and_with_odd_texts(spark, module):
    label = "toxic" if module is toxicity else "quality"
    none = spark.createDataFrame([], f"doc_id long, {label} int")
    got = module.classify(docs(spark, ODD, True), none).toPandas()
    assert len(got) == len(ODD) and (got.score == (module is quality)).all()


def brute(texts, n, num, den):
    sets = []
    for t in texts:
        w = (t or "").encode().lower().split()
        sets.append({tuple(w[i : i + n]) for i in range(len(w) - n + 1)} or ({tuple(w)} if w else set()))
    comp = list(range(len(texts)))
    for _ in texts:
        for i, a in enumerate(sets):
            for j in range(i):
                if a and sets[j] and den * len(a & sets[j]) >= num * len(a | sets[j]):
                    comp[i] = comp[j] = min(comp[i], comp[j])
    return [len(s) for s in sets], comp


@pytest.mark.parametrize(("n", "num"), [(3, 90), (5, 80)])
def test_join_equals_brute_force(spark, monkeypatch, n, num):
    rng = np.random.default_rng(n)
    vocab = np.array([f"w{i}" for i in range(400)])
    texts = [None, "", " \t", "one", "One", "two words", "two  words"]
    for _ in range(12):
        one = rng.choice(vocab, rng.integers(4, 160))
        texts.append(" ".join(one))
        for _ in range(rng.integers(0, 5)):
            other = one.copy()
            other[rng.integers(0, len(one), rng.integers(0, 1 + len(one) // 25))] = "edit"
            texts.append(" ".join(other))
    sizes, comp = brute(texts, n, num, 100)
    got = ngram_join.jaccard_components(docs(spark, texts, True), n, num, 100).orderBy("doc_id").collect()
    assert [r["n_shingles"] for r in got] == sizes
    assert [r["component_id"] for r in got] == comp
    # All rows twice, and ids shuffled to the texts in place of a broadcast.
    monkeypatch.setattr(ngram_join, "BROADCAST_ROWS", -1)
    again = ngram_join.jaccard_components(docs(spark, texts).union(docs(spark, texts)), n, num, 100).orderBy("doc_id").collect()
    assert [r["component_id"] for r in again] == [c for c in comp for _ in range(2)]


def test_second_round_links_what_the_first_classes_do_not(spark):
    # A chain in which neighbours link, and the ends do not: groups hold classes that link with some members only.
    base = [f"w{i}" for i in range(100)]
    texts = [" ".join(base[:i] + [f"x{k}" for k in range(i)] + base[i:]) for i in range(0, 12, 2)]
    sizes, comp = brute(texts, 3, 90, 100)
    got = ngram_join.jaccard_components(docs(spark, texts[::-1]), 3, 90, 100).orderBy("doc_id").collect()
    want = brute(texts[::-1], 3, 90, 100)
    assert [r["component_id"] for r in got] == want[1] and [r["n_shingles"] for r in got] == want[0]


def test_keep_one_keeps_empty_and_null_rows(spark):
    d = spark.createDataFrame([(3, "a b c d e f"), (1, "a b c d e f"), (1, "a b c d e f"), (2, ""), (4, None), (None, "a b c d e f")], "doc_id long, text string")
    kept = sorted((r["doc_id"] if r["doc_id"] is not None else -1) for r in ngram_join.keep_one(d).collect())
    assert kept == [-1, 1, 2, 4]
    assert ngram_join.keep_one(d.where("false")).count() == 0


def test_parts_find_every_pair_above_the_threshold():
    rng = np.random.default_rng(9)
    for num in (80, 90):
        parts = ngram_join.Parts(num, 100, np.sort(rng.integers(0, 2**63, 50).astype(np.uint64)))
        for _ in range(150):
            size = int(rng.integers(3, 400))
            a = rng.integers(0, 2**63, size).astype(np.uint64)
            drop = int(rng.integers(0, 1 + size // 8))
            b = np.concatenate((a[drop:], rng.integers(0, 2**63, int(rng.integers(0, 1 + size // 8))).astype(np.uint64)))
            both = len(np.intersect1d(a, b))
            if 100 * both >= num * (len(a) + len(b) - both) and both < len(a):
                assert len(np.intersect1d(parts.signatures(np.unique(a)), parts.signatures(np.unique(b))))
