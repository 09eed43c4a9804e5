"""Cases where operators used to differ by size or fail, and models against plain formulas."""

import math
import random
from types import SimpleNamespace

import numpy as np
import pyarrow as pa
from pyspark.sql import functions as F

from webgather.llm import decontaminate, langid, minhash, packing, pii, quality, queries

# 1


def test_blocks_of_items_give_what_one_does(spark):
    words = [f"w{i}" for i in range(400)]
    items = [(k, " ".join(words[20 * k : 20 * k + 18])) for k in range(12)] + [(12, None), (None, "w1 w2")]
    rng = random.Random(3)
    rows = [(7, " ".join(words[:60])), (7, " ".join(words[5:30])), (7, "w1"), (None, " ".join(words[100:140])), (None, None), (8, ""), (8, "x " * 50 + " ".join(words[200:240]))]
    rows += [(k, " ".join(rng.choice(words) for _ in range(30)) + " " + " ".join(words[(at := rng.randrange(300)) : at + 40])) for k in range(20, 40)]
    docs = spark.createDataFrame([(i, t, "x", 1) for i, t in rows], "doc_id long, text string, items string, n_hit int")
    table = spark.createDataFrame(items, "item_id long, text string")

    def of(most):
        got = [tuple(str(v) for v in r) for r in decontaminate.contamination(docs, table, most_bytes=most).collect()]
        kept = decontaminate.uncontaminated(docs, table, most_bytes=most)
        assert kept.columns == docs.columns
        return sorted(got), sorted(tuple(str(v) for v in r) for r in kept.collect())

    one, several = of(1 << 20), of(200)
    assert one == several and len(one[0]) == len(rows) and 0 < len(one[1]) < len(rows)


# 2


def plain_code_length(train, n_symbols, text, order):
    """Bits of text by escape method C with exclusion, contexts that start with nothing."""
    counts = {}
    for t in train:
        padded = [None] * order + list(t)
        for i in range(order, len(padded)):
            for k in range(order + 1):
                own = counts.setdefault(tuple(padded[i - k : i]), {})
                own[padded[i]] = own.get(padded[i], 0) + 1

    def chance(context, symbol):
        """Of each symbol the shorter context gives, with the seen ones left out where it escapes."""
        seen = counts.get(context)
        if seen is None:
            return 1 / n_symbols if not context else chance(context[1:], symbol)
        total, kinds = sum(seen.values()), len(seen)
        if symbol in seen:
            return seen[symbol] / (total + kinds)
        below = (lambda s: chance(context[1:], s)) if context else (lambda s: 1 / n_symbols)
        rest = 1 - sum(below(s) for s in seen)
        return kinds / (total + kinds) * below(symbol) / max(1e-9, rest)

    padded = [None] * order + list(text)
    return -sum(math.log2(chance(tuple(padded[i - order : i]), padded[i])) for i in range(order, len(padded)))


def test_code_lengths_against_the_plain_model():
    train = {"a": [b"abracadabra abracadabra", b"banana band"], "b": [b"xyzzy plugh xyzzy", b"a band of xylophones"]}
    trees = langid.ContextTrees(train)
    assert trees.bits.dtype == np.float64
    texts = [b"abra band", b"xyzzy", b"banana xylophones", b"dab", b"plugh of a"]
    data = np.frombuffer(b"".join(texts), np.uint8)
    got = trees.lengths(data, np.concatenate([[0], np.cumsum([len(t) for t in texts])]))
    for k, t in enumerate(texts):
        for g, lang in enumerate(trees.langs):
            # the symbol for bytes never seen is one more
            assert math.isclose(got[k, g], plain_code_length(train[lang], trees.n, t, 3), rel_tol=1e-6), (t, lang)


def test_a_repeated_id_without_language_is_not_learned_from(spark):
    docs = spark.createDataFrame([(1, "plain english words", "en"), (1, "no language here", None), (2, "mots en clair", "fr"), (2, None, "fr")], "doc_id long, text string, lang string")
    assert {(r["lang"], r["body"]) for r in langid.sample(docs, F.lit(True)).collect()} == {("en", "plain english words"), ("fr", "mots en clair")}
    assert langid.learn(docs, F.lit(True)).langs == ["en", "fr"]


# 3


def test_scores_against_the_plain_density():
    rng = np.random.default_rng(8)
    x = np.concatenate([rng.normal(0, 1, (60, 3)), rng.normal(1.2, 2, (90, 3))])
    y = np.repeat([0, 1], [60, 90])
    model = quality.fit(x, y)
    means, inverses = model.means, model.inverses
    z = np.clip((x - model.center) / model.scale, -8, 8)
    log = []
    for k in (0, 1):
        precision = inverses[k].T @ inverses[k]
        d = z - means[k]
        log.append(np.log((y == k).mean()) + 0.5 * np.linalg.slogdet(precision)[1] - 0.5 * np.einsum("ij,jk,ik->i", d, precision, d))
    assert np.allclose(model.score(x), 1 / (1 + np.exp(log[0] - log[1]))) and np.allclose(means[1], z[y == 1].mean(0))


def test_quality_with_narrow_ids(spark):
    docs = spark.createDataFrame([(k, "some words here " * (1 + k % 5)) for k in range(30)], "doc_id int, text string")
    labels = spark.createDataFrame([(k, int(k % 5 > 2)) for k in range(30)], "doc_id int, quality long")
    assert quality.score(docs, quality.learn(docs, labels, F.lit(True))).filter("score between 0 and 1").count() == 30


# 4


def test_candidates_share_a_band_and_survivors_pass_every_batch():
    rng = np.random.default_rng(6)
    x, y = rng.integers(0, 4, (20, 5)), rng.integers(0, 4, (30, 5))
    c, d = rng.integers(0, 9, 20), rng.integers(0, 9, 30)
    got = minhash.candidates(x, y, c, d)
    assert all(got[i, j] == ((x[i] == y[j]).any() and c[i] != d[j]) for i in range(20) for j in range(30))
    a = rng.integers(0, 256, (50, 128), dtype=np.uint8)
    b = np.where(rng.random((50, 128)) < np.linspace(0, 1, 50)[:, None], a, a + 1).astype(np.uint8)
    steps = minhash._steps(128, 0.75, 1e-6)
    want = [k for k in range(50) if all((a[k, :n] == b[k, :n]).sum() >= least for n, least in steps)]
    assert minhash.survivors(a, b, steps).tolist() == want and 0 < len(want) < 50


# 9


def test_contexts_are_whole_words():
    text = "telephone " + "." * 200 + " unprecedentedly" + " " * 45 + "212 555 0147"
    at = text.index("212")
    assert pii._contexts(text, at, len(text)) == ["<unprecedentedly", "<telephone unprecedentedly"]


def test_planted_identifiers_precision_and_recall(spark):
    """A third of the phone numbers lack the plus sign; orders and totals carry numbers of the same shape."""
    rng = random.Random(21)
    number = lambda: f"{rng.randrange(200, 999)} 555 0{rng.randrange(100, 999)}"
    rows, want = [], set()
    for k in range(600):
        n = number()
        if k % 3 == 0:
            rows.append(f"{rng.choice(['please', 'or', 'do'])} phone: {n} {rng.choice(['today', 'soon', 'later'])}")
            want.add(k)
        elif k % 3 == 1:
            rows.append(f"{rng.choice(['please', 'or', 'do'])} phone: +1 {n} {rng.choice(['today', 'soon', 'later'])}")
        else:
            rows.append(f"the {rng.choice(['order', 'total', 'invoice'])} {n} {rng.choice(['is', 'was'])} sent")
    rows += [rows[0], rows[0]]
    docs = spark.createDataFrame([(k if k < 600 else 0, t) for k, t in enumerate(rows)], "doc_id long, text string")
    got = pii.find_personal_data(docs, belief=0.45).filter("size(added) > 0").collect()
    found = {r["doc_id"] for r in got}
    assert len(found & want) >= 0.95 * len(want) and len(found - want) <= 0.02 * len(found)
    assert sum(r["doc_id"] == 0 for r in got) == 3  # equal rows stay apart


# 10


def test_folding_that_leaves_marks_uncomposed():
    from tokenizers import Tokenizer

    path = queries.tokenizer_path()
    plain, encode = Tokenizer.from_file(path), packing.Encoder(path)
    rng = random.Random(2)
    texts = ["İ्", "a İ् b", "İstanbul İ́"]
    texts += ["".join(rng.choice("İIıȩ्́ ,aéǅ") for _ in range(6)) for _ in range(2000)]
    for t in texts:
        assert encode(t) == np.array(plain.encode(t, add_special_tokens=False).ids, "<u4").tobytes(), ascii(t)


def test_words_with_marks_behind_are_the_whole_text():
    from tokenizers import Tokenizer

    path = queries.tokenizer_path()
    plain, encode = Tokenizer.from_file(path), packing.Encoder(path, 300)
    rng = random.Random(3)
    letters = ["The", "rock", "s", "t", "re", "ÀÉ", "ñandú", "µ", "ªº", "ß", "дом", "中文", "e\u0301", "Σας", "ﬁ"]
    marks = ["", "", ",", ".", "!!", "'", "''", ",!!", "_", "%%%", "<|", "|>", "…", "'s", "²", "7", "42", "\xb7", "\u00ad"]
    gaps = [" ", " ", "\n", "\t", "  ", "\xa0", "\x85", "\x1f", "", "\u2028"]
    for _ in range(3000):
        text = "".join(rng.choice(part) for _ in range(rng.randrange(9)) for part in (letters, marks, gaps))
        assert encode(text) == np.array(plain.encode(text, add_special_tokens=False).ids, "<u4").tobytes(), ascii(text)


def test_a_known_word_with_known_marks_is_not_encoded(monkeypatch):
    path = queries.tokenizer_path()
    encode = packing.Encoder(path)
    want = encode.whole("Palabra!! árbol,!!")
    encode("palabra árbol una!! dos,!!")

    def refused(*_):
        raise AssertionError("a word whose parts are known was sent to the tokenizer")

    monkeypatch.setattr(encode, "_learn", refused)
    assert encode("Palabra!! árbol,!!") == want


def test_swaps_of_many_pieces_and_classes():
    rng = random.Random(5)
    histogram = {n: rng.randrange(1, 40) for n in rng.sample(range(250, 1100), 300)}
    before = packing.best_fit(histogram, 2048)
    after = packing.swap_search(before, 2048)
    assert sum(after.values()) < sum(before.values())
    pieces = lambda bins: {x: n for x, n in sum((([(x, n) for x in b]) for b, n in bins.items()), [])}
    assert set(pieces(after)) == set(histogram)
    assert sum(len(b) * n for b, n in after.items()) == sum(histogram.values()) and all(sum(b) <= 2048 for b in after)
    few = packing.swap_search(before, 2048, steps=1)
    assert sum(after.values()) <= sum(few.values()) <= sum(before.values())


def test_language_keeps_workers_small(spark):
    """What packing keeps in a worker is gone when language identification begins there, and large batches leave in parts."""
    texts = ["plain english words " * 20_000, None, "mots en clair " * 30_000, "123", "plain words " * 40_000]
    batch = pa.RecordBatch.from_arrays([pa.array(range(5)), pa.array(texts, pa.string())], names=["doc_id", "text"])
    docs = SimpleNamespace(columns=["doc_id", "text"], schema=None, sparkSession=spark, mapInArrow=lambda f, schema: f)
    trees = langid.ContextTrees({"en": [b"plain english words"], "fr": [b"mots en clair"]})
    packing._encoder(queries.tokenizer_path())
    parts = list(langid.recognised(docs, trees)(iter([batch])))
    assert packing._encoder.cache_info().currsize == 0
    assert [x for p in parts for x in p.column(0).to_pylist()] == [0, 2, 4]
    assert len(parts) > 1 and all(sum(map(len, p.column(1).to_pylist())) <= 1 << 20 for p in parts)
