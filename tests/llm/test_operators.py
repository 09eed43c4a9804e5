"""The ten operators on odd input, against brute force, and on the smallest tables."""

import hashlib
import random
import re

import numpy as np
import pyarrow as pa
import pytest
from helpers import SMALL, rows_of
from pyspark.sql import functions as F

from webgather.llm import components, decontaminate, exact_dedup, langid, minhash, packing, pii, quality, queries, repeats, sketch, sql, substring, suffix, toolcalls


def docs_of(spark, texts):
    return spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")


@pytest.mark.parametrize("name", sorted(sql.ORACLES))
def test_oracle(spark, duck, name):
    assert rows_of(queries.QUERIES[name](spark, SMALL).toPandas()) == rows_of(duck.sql(sql.ORACLES[name]).df())


def mutated(rng, n=40):
    """Texts with copies, near copies and shared passages."""
    word = lambda: "".join(rng.choice("abcdé") for _ in range(rng.randrange(2, 9)))
    base = [[word() for _ in range(rng.randrange(3, 120))] for _ in range(n // 4)]
    out = [" ".join(b) for b in base]
    while len(out) < n:
        w = list(rng.choice(base))
        for _ in range(rng.randrange(4)):
            w[rng.randrange(len(w))] = word()
        if rng.random() < 0.4:
            b = rng.choice(base)
            w = [word() for _ in range(rng.randrange(9))] + b[rng.randrange(len(b)) :] + w[: rng.randrange(1, 40)]
        out.append(rng.choice([" ", "  ", "\n"]).join(w))
    return out


# 1


def test_decontaminate_against_brute_force(spark):
    rng = random.Random(1)
    texts = mutated(rng)
    items = [" ".join(t.split()[5:40]) for t in texts[:6]] + ["short item", "", None, texts[7].upper()]
    table = spark.createDataFrame([(i, t) for i, t in enumerate(items)], "item_id long, text string")
    words = lambda t: re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
    for most in (1 << 20, 600):  # one block, and several
        got = {r["doc_id"]: r for r in decontaminate.contamination(docs_of(spark, texts + ["SHORT, item!"]), table, most_bytes=most).collect()}
        for k, t in enumerate(texts + ["SHORT, item!"]):
            w, hit, ids = words(t), set(), set()
            for i, item in enumerate(items):
                v = words(item)
                n = min(13, len(v))
                for a in range(len(v) - n + 1 if v else 0):
                    for b in range(len(w) - n + 1):
                        if w[b : b + n] == v[a : a + n]:
                            hit.update(range(b, b + n))
                            ids.add(str(i))
            assert (got[k]["n_words"], got[k]["n_hit"], got[k]["items"]) == (len(w), len(hit), sorted(ids))
            spans = [t[s["start"] : s["end"]] for s in got[k]["spans"]]
            assert sum(len(words(s)) for s in spans) == len(hit)


def test_decontaminate_odd(odd_docs, no_docs, spark):
    items = spark.createDataFrame([(1, None), (None, "x x x"), (2, "one two")], "item_id long, text string")
    got = decontaminate.flagged(decontaminate.contamination(odd_docs, items))
    assert got.count() == odd_docs.count() and {r["doc_id"] for r in got.filter("contaminated").collect()} == {8, 9}
    assert decontaminate.contamination(no_docs, items).count() == 0 and decontaminate.contamination(odd_docs, items.limit(0)).filter("n_hit > 0").count() == 0


# 2


def test_language_held_out(spark):
    docs = queries.table(spark, "/root/testdata/sf0.01", "documents")
    got = queries.op2_language(spark, "/root/testdata/sf0.01").join(docs.select("doc_id", "lang"), "doc_id").filter("held_out")
    assert got.filter("lang = lang_pred").count() >= 0.97 * got.count()
    assert got.filter("score < 0 or score > 1").isEmpty()


def test_code_lengths_sum_to_probabilities():
    trees = langid.ContextTrees({"a": [b"abracadabra abracadabra"], "b": [b"xyzzy plugh xyzzy"]})
    p = np.exp2(-trees.bits.astype(np.float64)).reshape(-1, trees.n, 2).sum(1)
    assert np.allclose(p, 1, atol=0.02)


def test_language_odd(odd_docs, no_docs, spark):
    trees = langid.learn(odd_docs, F.lit(True))
    got = {r["doc_id"]: r["lang_pred"] for r in langid.identify(odd_docs, trees).collect()}
    assert got[5] == got[6] == got[7] == "und" and got[12] == "es"
    assert langid.recognised(odd_docs, trees).columns == odd_docs.columns and langid.identify(no_docs, trees).count() == 0
    none = langid.learn(no_docs, F.lit(True))
    assert {r["lang_pred"] for r in langid.identify(odd_docs, none).collect()} == {"und"}


# 3


def test_quality_held_out(spark):
    sf = "/root/testdata/sf0.01"
    got = queries.op3_quality(spark, sf).join(queries.table(spark, sf, "labels"), "doc_id").filter("held_out").toPandas()
    good, bad = got[got.quality == 1].score.to_numpy(), got[got.quality == 0].score.to_numpy()
    assert (good[:, None] > bad[None, :]).mean() > 0.95


def test_quality_odd(odd_docs, no_docs, spark):
    labels = spark.createDataFrame([(1, 1), (1, 0), (5, None), (None, 1)], "doc_id long, quality int")
    model = quality.learn(odd_docs, labels, F.lit(True))
    assert quality.score(odd_docs, model).filter("score between 0 and 1").count() == odd_docs.count()
    assert quality.learn(no_docs, labels.limit(0), F.lit(True)).flat == 0.5 and quality.score(no_docs, model).count() == 0


# 4


def shingle_set(text):
    w = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
    return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()


def brute_components(texts):
    sets = [shingle_set(t) for t in texts]
    root = list(range(len(texts)))

    def top(x):
        while root[x] != x:
            x = root[x]
        return x

    for a in range(len(texts)):
        for b in range(a):
            if sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= 75 * len(sets[a] | sets[b]):
                x, y = sorted((top(a), top(b)))
                root[y] = x
    return [(len(sets[k]), top(k)) for k in range(len(texts))]


@pytest.mark.parametrize("seed", [1, 2])
def test_near_duplicates_against_all_pairs(spark, seed):
    rng = random.Random(seed)
    texts = mutated(rng, 60)
    base = [f"t{i}" for i in range(80)]
    for _ in range(60):  # a group of copies, many of them under the threshold of each other
        w = list(base)
        for _ in range(rng.randrange(5)):
            w[rng.randrange(80)] = f"n{rng.randrange(10**6)}"
        texts.append(" ".join(w))
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in minhash.near_duplicates(docs_of(spark, texts)).collect()}
    assert [got[k] for k in range(len(texts))] == brute_components(texts)


def test_near_duplicates_odd(odd_docs, no_docs):
    got = minhash.near_duplicates(odd_docs)
    assert got.count() == odd_docs.count()
    by = {r["doc_id"]: r for r in got.collect()}
    assert by[2]["component_id"] == 1 == by[4]["component_id"] and by[9]["component_id"] == 8 and by[5]["n_shingles"] == 0 and by[6]["kept"] and by[None]["component_id"] == 1
    assert minhash.near_duplicates(no_docs).count() == 0


def test_sequential_bound():
    assert minhash.least_matches(32, 0.75, 1e-6) < minhash.least_matches(32, 0.75, 1e-2) <= 24
    assert 0.5 < minhash.least_matches(1000, 0.75, 1e-6) / 1000 < 0.75


def test_block_comparison_is_all_pairs():
    rng = np.random.default_rng(2)
    sets = [set(rng.integers(0, 30, rng.integers(5, 25)).tolist()) for _ in range(40)]
    owner = np.repeat(np.arange(40), [len(s) for s in sets])
    term = np.concatenate([sorted(s) for s in sets])
    n, c = np.array([len(s) for s in sets]), np.arange(40)
    found = minhash.verified_links(owner, term, n, c, np.arange(40), np.arange(40), 50, 100, np.ones((40, 40), bool), width=7)
    links = {(i, j) for i in range(40) for j in range(i) if 100 * len(sets[i] & sets[j]) >= 50 * len(sets[i] | sets[j])}
    assert {tuple(sorted(p, reverse=True)) for p in found} <= links

    def parts(pairs):
        root = list(range(40))
        for i, j in pairs:
            a, b = root[i], root[j]
            root = [a if r == b else r for r in root]
        return [{k for k in range(40) if root[k] == root[i]} for i in range(40)]

    assert parts(found) == parts(links)


def test_components(spark):
    rng = random.Random(4)
    pairs = [(rng.randrange(60), rng.randrange(60)) for _ in range(45)] + [(k, k + 1) for k in range(100, 140)]
    root = {}
    for a, b in pairs:
        root.setdefault(a, {a})
        root.setdefault(b, {b})
        both = root[a] | root[b]
        for x in both:
            root[x] = both
    got = {r["node"]: r["component_id"] for r in components.components(spark.createDataFrame(pairs, "a long, b long")).collect()}
    assert got == {k: min(v) for k, v in root.items() if len(v) > 1}


def test_components_ask_little_of_the_driver(spark):
    """A star, a long chain, random links and links met twice: stars by tasks, and few jobs, as each leaves something on the driver."""
    rng = random.Random(8)
    order = rng.sample(range(5000, 5400), 400)
    pairs = [(7, k) for k in range(1000, 1800)] + list(zip(order, order[1:])) + [(rng.randrange(9000, 9500), rng.randrange(9000, 9500)) for _ in range(300)] + [(1, 1), (3, 2), (2, 3), (3, 2)]
    top = {}

    def of(x):
        while top.get(x, x) != x:
            x = top[x]
        return x

    for a, b in pairs:
        if a != b:
            x, y = of(a), of(b)
            top[max(x, y)] = min(x, y)
    edges = spark.createDataFrame(pairs, "a long, b long").repartition(9)
    spark.sparkContext.setJobGroup("components", "")
    found = components.components(edges).collect()
    jobs = len(spark.sparkContext.statusTracker().getJobIdsForGroup("components"))
    spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)
    assert {r["node"]: r["component_id"] for r in found} == {k: of(k) for a, b in pairs if a != b for k in (a, b)}
    assert len(found) == len({r["node"] for r in found})
    assert jobs <= 50, jobs


def test_stars_of_a_task_in_parts():
    """Parts merged on the way give what one does, and a node that came as an a stays marked."""
    rng = np.random.default_rng(3)
    x, y = rng.integers(0, 3000, 4000), rng.integers(0, 3000, 4000)
    a, b = np.maximum(x, y)[x != y], np.minimum(x, y)[x != y]
    batches = [pa.RecordBatch.from_arrays([pa.array(a[k : k + 300]), pa.array(b[k : k + 300])], names=["a", "b"]) for k in range(0, len(a), 300)]
    one, parts = (pa.Table.from_batches(components._contracted(batches, most)).to_pydict() for most in (1 << 20, 500))
    assert one == parts
    assert [k in set(a.tolist()) for k in one["a"]] == one["own"] and not all(one["own"])
    assert all(r < k for k, r in zip(one["a"], one["b"])) and not set(one["a"]) & set(one["b"])


# 5


def test_tool_calls(spark):
    m = "conv_id long, turn long, role string, text string, call_id string, name string, arguments string, refs array<string>"
    rows = [
        (1, 0, "assistant", None, "a", "f", '{"y": 2, "x": "t"}', []), (1, 1, "tool", "result \"a\"\n", "a", None, None, None), (1, 2, "assistant", None, "b", "f", '{"x": 3}', ["a"]), (1, 3, "tool", "late", "b", None, None, None),
        (1, 4, "assistant", None, "a", "f", "[1]", []), (1, 5, "tool", "nobody asked", "z", None, None, None), (1, 6, "user", "hello", None, None, None, None), (1, 7, "assistant", None, "p", "g", "{", ["q"]), (1, 8, "assistant", None, "q", "f", '{"x": "1", "w": 1}', ["p"]),
        (1, 9, "tool", "x", "p", None, None, None), (1, 10, "tool", "x", "q", None, None, None), (None, None, None, None, None, None, None, None), (2, 0, "tool", "first", "k", None, None, None), (2, 1, "assistant", None, "k", "f", '{"x": "v"}', []),
    ]
    got = toolcalls.format_calls(spark.createDataFrame(rows, m), {"f": {"x": ("STRING", True), "y": ("BIGINT", False)}}).toPandas()
    one = got[got.conv_id == 1].sort_values("turn")
    assert one.status.tolist() == ["linked", "linked", "linked", "linked", "repeated", "orphan", "message", "circular", "circular", "linked", "linked"]
    assert one.valid.tolist()[:5] == [True, True, False, True, False] and not one.valid.tolist()[7] and not one.valid.tolist()[8]
    assert one.line.iloc[0] == '{"arguments":{"x":"t","y":2},"id":"a","name":"f","role":"assistant"}'
    assert one.line.iloc[1] == '{"content":"result \\"a\\"\\n","id":"a","role":"tool"}'
    two = got[got.conv_id == 2].sort_values("position")
    assert two.turn.tolist() == [1, 0] and len(got) == len(rows)
    assert sorted(one.position) == list(range(11))
    assert toolcalls.format_calls(spark.createDataFrame([], m), {}).count() == 0


def test_tool_calls_follow_what_they_refer_to(spark):
    m = "conv_id long, turn long, role string, text string, call_id string, name string, arguments string, refs array<string>"
    call = lambda c, t, i, *refs: (c, t, "assistant", None, i, "f", "{}", list(refs))
    result = lambda c, t, i: (c, t, "tool", "x", i, None, None, None)
    rows = [
        call(1, 1, "a"), call(1, 4, "b", "a"), (1, 5, "user", "hi", None, None, None, None), result(1, 6, "b"), result(1, 7, "a"),
        call(2, 1, "d", "e", None), result(2, 2, "d"), call(2, 3, "f", "d"), result(2, 4, "f"), call(2, 8, "e"), result(2, 9, "e"), call(2, 10, "g", "nobody"), result(2, 11, "g"),
        call(4, 0, "o", "z"), result(4, 3, "z"), result(4, 4, "o"),
    ]
    chain = 40
    for k in range(chain):  # the later in the chain, the earlier its turn
        rows += [call(3, 2 * (chain - k), f"k{k}", *([f"k{k - 1}"] if k else [])), result(3, 2 * (chain - k) + 1, f"k{k}")]
    got = toolcalls.format_calls(spark.createDataFrame(rows, m), {}).toPandas().sort_values(["conv_id", "position"])
    assert set(got.status) == {"linked", "message", "orphan"} and len(got) == len(rows)
    order = {c: list(zip(g.call_id, g.kind, strict=True)) for c, g in got.groupby("conv_id")}
    assert order[1] == [("a", "call"), (None, "message"), ("a", "result"), ("b", "call"), ("b", "result")]
    assert order[2] == [(i, kind) for i in "edfg" for kind in ("call", "result")]
    assert order[3] == [(f"k{k}", kind) for k in range(chain) for kind in ("call", "result")]
    assert order[4] == [("z", "result"), ("o", "call"), ("o", "result")]


# 6


def test_exact_groups_odd(odd_docs, no_docs):
    rows = [(r["doc_id"], r["text"] or "") for r in odd_docs.collect()]
    got = exact_dedup.exact_groups(odd_docs, keep="largest").collect()
    assert len(got) == len(rows)
    for r in got:
        same = [i for i, t in rows if hashlib.sha256(t.encode()).hexdigest() == r["text_sha256"]]
        assert r["group_size"] == len(same) and r["keep_id"] == max(i for i in same if i is not None) and r["kept"] == (r["doc_id"] == r["keep_id"])
    assert exact_dedup.exact_groups(no_docs).count() == 0
    assert exact_dedup.drop_exact_copies(odd_docs).columns == odd_docs.columns


# 7 and 8


def brute_windows(texts, size=20):
    seen, out = set(), []
    for t in texts:
        w = re.findall(r"[^\x20\x09-\x0D]+", t or "")
        gone = set()
        for i in range(len(w) - size + 1):
            key = tuple(w[i : i + size])
            if key in seen:
                gone.update(range(i, i + size))
            seen.add(key)
        out.append((len(w), len(gone), " ".join(x for i, x in enumerate(w) if i not in gone)))
    return out


def brute_bytes(texts, size=50):
    seen, out = set(), []
    for t in texts:
        b = (t or "").encode()
        mine = [b[i : i + size] for i in range(len(b) - size + 1)]
        gone = {j for i, k in enumerate(mine) if k in seen for j in range(i, i + size)}
        seen.update(mine)
        out.append((len(b), len(gone), sum(i not in {j + 1 for j in gone} for i in gone), bytes(x for i, x in enumerate(b) if i not in gone)))
    return out


def test_substrings_against_brute_force(spark):
    texts = mutated(random.Random(9), 50) + ["same words again and " * 30, "no " * 19, "yes " * 45, None, ""]
    got = {r["doc_id"]: (r["n_words"], r["n_removed"], r["kept_text"]) for r in substring.remove_repeated_windows(docs_of(spark, texts)).collect()}
    assert [got[k] for k in range(len(texts))] == brute_windows(texts)


@pytest.mark.parametrize("hot", [2000, 1])
def test_strings_against_brute_force(spark, hot):
    texts = mutated(random.Random(10), 50) + ["abc" * 60, "xabc" * 50, "abc" * 90, "é" * 120, "é" * 60, None, "\x00" * 60 + "a", "\x00" * 70]
    got = {r["doc_id"]: (r["n_bytes"], r["n_removed"], len(r["spans"]), bytes(r["kept"])) for r in suffix.remove_earlier_strings(docs_of(spark, texts), hot=hot, shard_bytes=3000).collect()}
    assert [got[k] for k in range(len(texts))] == brute_bytes(texts)


def test_substrings_odd(odd_docs, no_docs):
    for f, n in ((substring.remove_repeated_windows, "n_words"), (suffix.remove_earlier_strings, "n_bytes")):
        got = f(odd_docs).collect()
        by = {r["doc_id"]: r for r in got}
        assert len(got) == odd_docs.count() and by[None]["n_removed"] == 0 and by[2]["n_removed"] == by[2][n] and by[1]["n_removed"] == 0 and by[5][n] == 0
        assert f(no_docs).count() == 0


def test_long_rows_are_cut_into_stretches():
    rng = np.random.default_rng(3)
    data = np.frombuffer(bytes(rng.integers(97, 100, 5000, dtype=np.uint8)), np.uint8)
    items = repeats.Items("bytes", 20, data, np.array([0, 1200, 1230, 5000]))
    covered = [(s + k) for _, starts, counts, _, _ in repeats.runs(items, 50) for s, c in zip(starts, counts, strict=True) for k in range(c)]
    assert sorted(covered) == [*range(0, 1151), *range(1230, 4951)]


def test_runs_after_empty_rows_keep_their_document():
    rng = np.random.default_rng(4)
    texts = [bytes(rng.integers(97, 123, n, dtype=np.uint8)).decode() for n in (300, 220, 0, 180, 0, 0, 400)]
    texts[6] = texts[3] + texts[6]
    offsets = np.concatenate([[0], np.cumsum([len(t) for t in texts])])
    items = repeats.Items("bytes", 20, np.frombuffer("".join(texts).encode(), np.uint8), offsets)
    for most in (0, 540, 250):
        got = {(int(d), int(s - o[d]) + k) for doc, starts, counts, _, o in repeats.runs(items, 50, most) for d, s, c in zip(doc, starts, counts, strict=True) for k in range(c)}
        assert got == {(d, k) for d, t in enumerate(texts) for k in range(len(t) - 49)}


def test_strings_after_empty_rows_of_a_cut(spark):
    rng = random.Random(14)
    text = lambda n: "".join(rng.choices("abcdefghijklmnop", k=n))
    shared = text(400)
    texts = [shared, text(300_000), text(220_000), None, text(500) + shared + text(90_000), "", text(7) + shared]
    rows = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").coalesce(1)
    got = {r["doc_id"]: (r["n_bytes"], r["n_removed"], len(r["spans"]), bytes(r["kept"])) for r in suffix.remove_earlier_strings(rows).collect()}
    want = [(len(t or ""), 400 * (k in (4, 6)), int(k in (4, 6)), (t or "").replace(shared, "" if k else shared).encode()) for k, t in enumerate(texts)]
    assert [got[k] for k in range(len(texts))] == want


def test_packed_rows_are_narrow_and_whole():
    rng = np.random.default_rng(5)
    for lead in (0, -(1 << 63), (1 << 63) - 9000, -4000):
        n = 20_000
        rows = np.empty(n, repeats.RUN)
        rows["fp"], rows["r"] = repeats.anchor_key(rng.integers(0, 1 << 64, n, np.uint64)), rng.integers(0, 1 << 64, n, np.uint64)
        rows["doc"], rows["s"], rows["n"] = lead + rng.integers(0, 8000, n), rng.integers(0, 60_000, n), rng.integers(1, 32, n)
        bucket = rng.integers(0, 50, n).astype(np.int32)
        groups = [repeats.packed(0, rows[:9000], bucket[:9000]), repeats.packed(0, rows[9000:], bucket[9000:]), repeats.packed(1, repeats.repeats_of(rows["doc"], rows["s"], 1), bucket)]
        blobs = repeats.blob_batch(*groups)
        assert np.array_equal(np.sort(repeats._gathered([blobs], repeats.RUN, 0)), np.sort(rows))
        found = repeats._gathered([blobs], repeats.FOUND, 1)
        assert np.array_equal(np.sort(found), np.sort(repeats.repeats_of(rows["doc"], rows["s"], 1)))
        runs, ends = (sum(len(x.as_py()) for k, x in zip(blobs.column(0).to_pylist(), blobs.column(2), strict=True) if k == kind) for kind in (0, 1))
        assert runs < 19 * n and ends < 6 * n
    assert repeats.packed(1, repeats.repeats_of(*(np.empty(0, int),) * 3), np.empty(0, np.int32)) == ([], [], [])


def test_only_texts_and_spans_are_left_to_shuffle(spark):
    shared = " ".join(f"share{i}" for i in range(60))
    docs = spark.createDataFrame([(1, shared), (2, "x" + shared[:200]), (3, "y" + shared[100:] + "z")], "doc_id long, text string")
    for f in (substring.remove_repeated_windows, suffix.remove_earlier_strings):
        cut = f(docs)
        assert "bucket" not in cut._jdf.queryExecution().executedPlan().toString()
        assert {r["doc_id"]: r["n_removed"] > 0 for r in cut.collect()} == {1: False, 2: True, 3: True}


def test_texts_and_spans_are_joined_alike_at_any_size(spark):
    """A few spans were broadcast and many weren't, so that what little input sent told nothing of more."""
    shared = " ".join(f"share{i}" for i in range(60))
    docs = spark.createDataFrame([(1, shared), (2, "x " + shared), (None, shared)], "doc_id long, text string")
    for f in (substring.remove_repeated_windows, suffix.remove_earlier_strings):
        cut = f(docs)
        assert sorted(r["n_removed"] > 0 for r in cut.collect()) == [False, False, True]
        plan = cut._jdf.queryExecution().executedPlan().toString()
        assert "SortMergeJoin" in plan and "BroadcastHashJoin" not in plan


def test_suffix_array_and_prefixes():
    rng = np.random.default_rng(5)
    for _ in range(20):
        s = rng.integers(1, 4, rng.integers(1, 200)).astype(np.uint16)
        s[rng.random(len(s)) < 0.1] = 0
        order = suffix.suffix_array(s)
        assert order.tolist() == sorted(range(len(s)), key=lambda i: s[i:].tolist())
        shared = suffix.common_prefixes(s, order, 12, lanes=3)
        for k in range(1, len(s)):
            a, b, n = s[order[k - 1] :].tolist(), s[order[k] :].tolist(), 0
            while n < 12 and n < min(len(a), len(b)) and a[n] == b[n] != 0:
                n += 1
            assert shared[k] == n


def test_records_alike_need_few_rounds(monkeypatch):
    """Separators differ by place: 400 equal records are ordered by rounds of a record's length, not of the whole text's."""
    rng = np.random.default_rng(6)
    for s in ([1, 2, 3, 1, 2, 1, 1, 3, 2, 0] * 400, [0, 0, 0], [1, 0], [2], [], rng.integers(0, 300, 5000).tolist(), rng.integers(0, 2, 3000).tolist() + [0]):
        x, at = np.array(s, np.uint16), np.append(np.flatnonzero(np.array(s) == 0), len(s))
        ends = at[np.searchsorted(at, np.arange(len(s)))]
        assert suffix.suffix_array(x, apart=True).tolist() == sorted(range(len(s)), key=lambda i: (s[i : ends[i]] + [0], ends[i]))
    x, sorts = np.array([1, 2, 3, 1, 2, 1, 1, 3, 2, 0] * 400, np.uint16), []
    monkeypatch.setattr(suffix.np, "flatnonzero", lambda a, f=np.flatnonzero: sorts.append(len(a)) or f(a))
    records = np.zeros(400, suffix.RECORD)
    records["size"], records["doc"] = 9, np.arange(400)
    shard = suffix.Shard(records, np.tile(np.array([1, 2, 3, 1, 2, 1, 1, 3, 2], np.uint8), 400), 9)
    assert len(shard.repeats()) == 399 and len(sorts) < 12


def test_sketch_never_undercounts(spark):
    rows = spark.range(4000).select(F.col("id"), (F.col("id") % 3000).alias("k")).repartition(7)
    keys = lambda b: [np.asarray(b.column(1)).astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)]
    for bits in (8, 14, 26):
        found = sketch.marked_keys(rows, keys, 2, bits, flush=300)
        got = found(np.arange(3000, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15))
        assert got[:1000].all() and (bits < 26 or not got[1000:].any())


# 9


def plain_base(text):
    out = [("email", *m.span()) for m in re.finditer(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", text)]
    out += [("ip", *m.span()) for m in re.finditer(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", text) if all(int(p) < 256 for p in m[0].split("."))]

    def luhn(d):
        return sum(x if i % 2 == 0 else x * 2 - 9 * (x > 4) for i, x in enumerate(map(int, reversed(d)))) % 10 == 0

    out += [("card", *m.span()) for m in re.finditer(r"[0-9]([\x20-]?[0-9])+", text) if 13 <= len(d := re.sub(r"\D", "", m[0])) <= 19 and luhn(d)]
    return out + [("phone", *m.span()) for m in re.finditer(r"\+[0-9][\x20().0-9-]+[0-9]", text) if 9 <= len(re.sub(r"\D", "", m[0])) <= 15]


def test_fixed_forms():
    rng = random.Random(11)
    parts = ["a.b@c.de", "x@y", "@z.com", "q@@r.st.uv", "10.0.0.255", "1.2.3.256", "1.2.3.4.5.6.7.8", "4111 1111 1111 1111", "4111-1111-1111-1112", "+1 (212) 555-0100", "+44.20", "4111111111111111", "é@è.fr", "word", ".", "-", "+", "9"]
    for _ in range(3000):
        text = "".join(rng.choice(parts) + rng.choice(["", " ", ",", "\n"]) for _ in range(rng.randrange(1, 7)))
        assert pii.base_spans(text) == plain_base(text), text


def test_contexts_find_unseen_identifiers(spark):
    rng = random.Random(12)
    rows = [f"please telephone: +1 (212) 555-0{rng.randrange(100, 999)} today number {k}" for k in range(40)]
    rows += ["please telephone: 212 555 0147 today", "the total 212 555 0148 of it", "mail ann (at) example.org now"]
    got = {r["doc_id"]: [tuple(x) for x in r["added"]] for r in pii.find_personal_data(docs_of(spark, rows)).collect()}
    assert got[40] == [("phone", 18, 30)] and got[41] == [] and not any(got[k] for k in range(40))


def test_personal_data_odd(odd_docs, no_docs):
    got = pii.find_personal_data(odd_docs)
    assert got.count() == odd_docs.count() and got.filter("size(seeds) + size(added) > 0").isEmpty() and pii.find_personal_data(no_docs).count() == 0


# 10


def test_packing_round_trip(spark):
    from tokenizers import Tokenizer

    path = queries.tokenizer_path()
    plain = Tokenizer.from_file(path)
    rng = random.Random(13)
    texts = mutated(rng, 80) + ["", None, "Can't, won't. Á İstanbul ΑΣ. <|endoftext|> it's", "a\x1cb c d", "word, " * 3000]
    got = packing.pack(docs_of(spark, texts), path, 256).toPandas()
    assert (got.groupby("sequence_id").length.sum() <= 256).all()
    for _, g in got.groupby("sequence_id"):
        g = g.sort_values("offset")
        assert g.offset.tolist() == [0, *np.cumsum(g.length)[:-1]]
    import zlib

    for k, t in enumerate(texts):
        ids = plain.encode(t or "", add_special_tokens=False).ids + [0]
        own = got[got.doc_id == k].sort_values("piece")
        assert own.start.tolist() == list(range(0, len(ids), 256)) and own.length.sum() == len(ids)
        assert own.ids_crc32.tolist() == [zlib.crc32(np.array(ids[a : a + 256], "<u4").tobytes()) for a in own.start]


def test_packing_odd(odd_docs, no_docs):
    got = packing.pack(odd_docs, queries.tokenizer_path())
    assert got.filter("piece = 0").count() == odd_docs.count() and packing.pack(no_docs, queries.tokenizer_path()).count() == 0


@pytest.mark.parametrize("seed", range(6))
def test_swaps_help_and_keep_all(seed):
    rng = random.Random(seed)
    lengths = [rng.choice([60, 51, 49, 41, 40, 35, 26, 25, 20]) for _ in range(rng.randrange(3, 60))]
    histogram = {n: lengths.count(n) for n in set(lengths)}
    before = packing.best_fit(histogram, 100)
    after = packing.swap_search(before, 100)
    for bins in (before, after):
        assert all(sum(b) <= 100 for b in bins) and sorted(x for b, n in bins.items() for x in b * n) == sorted(lengths)
    fill = lambda bins: sum(n * sum(b) ** 2 for b, n in bins.items())
    assert sum(after.values()) <= sum(before.values()) and fill(after) >= fill(before)


def test_swaps_empty_a_bin():
    from collections import Counter

    assert sum(packing.swap_search(Counter({(6, 2): 1, (5, 3): 1, (4,): 1}), 10).values()) == 2


# pipeline


def test_pipeline(spark):
    import corpus_pipeline as p

    docs = queries.table(spark, SMALL, "documents")
    names = docs.columns
    want = docs.toPandas()
    want = want[[any(map(str.isalpha, t or "")) for t in want.text]]
    want = want.sort_values("doc_id").drop_duplicates("text", keep="last")
    ids, texts = want.doc_id.tolist(), want.text.tolist()
    keep = [ids[k] for k, (_, top) in enumerate(brute_components(texts)) if top == k]
    now = docs
    for name, stage in p.STAGES[:4]:
        now = stage(spark, now, SMALL)
        assert now.columns == names, name
        if name == "near deduplication":
            assert sorted(r["doc_id"] for r in now.collect()) == sorted(keep)
    assert p.run(spark, SMALL).select("doc_id").distinct().count() == now.count()


def test_pipeline_null_and_repeated_ids(spark):
    import corpus_pipeline as p

    words = lambda a, n=60: " ".join(f"{a}word{i}" for i in range(n))
    edited = words("near").replace("nearword30", "other")
    rows = [
        (None, words("clean")), (None, words("lone")), (None, words("lone")), (1, words("twice")), (1, words("twice")), (2, words("loses")), (3, words("loses")), (2, words("stays")),
        (None, words("loses")), (4, words("near")), (5, edited), (5, words("apart")), (None, edited + " more"), (6, words("six")),
    ]
    docs = spark.createDataFrame([(i, t, "x") for i, t in rows], "doc_id long, text string, source string")
    exact = {(None, words("clean")), (None, words("lone")), (1, words("twice")), (3, words("loses")), (2, words("stays")), (4, words("near")), (5, edited), (5, words("apart")), (None, edited + " more"), (6, words("six"))}
    now = p.drop_copies(spark, p.written(docs), SMALL)
    got = [(r["doc_id"], r["text"]) for r in now.collect()]
    assert now.columns == docs.columns and len(got) == len(exact) and set(got) == exact
    near = exact - {(5, edited), (None, edited + " more")}
    for start in (now, docs):  # near copies alone, too, keep one of repeated rows, an id before a null and a smaller one
        now = p.drop_near_copies(spark, p.written(start), SMALL)
        got = [(r["doc_id"], r["text"]) for r in now.collect()]
        want = near if start is not docs else near - {(3, words("loses"))} | {(2, words("loses"))}
        assert now.columns == docs.columns and len(got) == len(want) and set(got) == want
    assert p.drop_contaminated(spark, now, SMALL).count() == len(near)
