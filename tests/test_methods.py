"""Brute force and worked cases for the methods."""

import itertools
import math
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from webgather.functions import html, suffix, urls
from webgather.operators import cache, centrality, crawl, dedup, feeder, fetchsim, filters, graph, lanes, powerlaw, ring, robots, seen, spill
from webgather.operators.filters import ResponseFilter, UrlFilter


def one(spark, value, make):
    return spark.createDataFrame([(value,)], "v string").select(make(F.col("v")).alias("r")).first()["r"]


@pytest.mark.parametrize(
    ("url", "normal"),
    [
        ("HTTP://Example.COM:80/a/./b/../c#x", "http://example.com/a/c"),
        ("https://h:443", "https://h/"),
        ("http://h:8080/", "http://h:8080/"),
        ("http://u@h/%7euser/%2f%C3%a9", "http://u@h/~user/%2F%C3%A9"),
        ("http://h/../../a", "http://h/a"),
        ("http://h/a b/é?q=ü", "http://h/a%20b/%C3%A9?q=%C3%BC"),
        ("http://h/%zz", "http://h/%25zz"),
        ("http://h?q=1", "http://h/?q=1"),
        ("http://h/a/..", "http://h/"),
    ],
)
def test_normal_form(spark, url, normal):
    assert one(spark, url, urls.normalise) == normal
    assert one(spark, normal, urls.normalise) == normal


@pytest.mark.parametrize(
    ("href", "target"),
    [("", "http://h/d/p?q"), ("http://x/y", "http://x/y"), ("//x/y", "http://x/y"), ("/y", "http://h/y"), ("y", "http://h/d/y"), ("../y", "http://h/y"), ("?z", "http://h/d/p?z"), ("#f", "http://h/d/p?q#f"), ("mailto:a@b", "mailto:a@b")],
)
def test_resolve(spark, href, target):
    assert one(spark, href, lambda c: urls.resolve(F.lit("http://h/d/p?q"), c)) == target


def test_query_options(spark):
    assert one(spark, "http://h/?b=1&utm=2&a=3", lambda c: urls.normalise(c, sort_query=True, drop_params=("utm",))) == "http://h/?a=3&b=1"


def test_registrable(spark):
    want = {"a.b.co.uk": "b.co.uk", "co.uk": None, "x.com": "x.com", "www.ck": "www.ck", "a.www.ck": "www.ck", "q.foo.ck": "q.foo.ck", "foo.ck": None, "1.2.3.4": "1.2.3.4", "u.pages.example.net": "u.pages.example.net", "a.unknown": "a.unknown"}
    got = suffix.registrable(spark.createDataFrame([(h,) for h in want], "h string"), "h", suffix.rules(spark)).collect()
    assert {r["host"]: r["domain"] for r in got} == want
    public = suffix.registrable(spark.createDataFrame([("u.pages.example.net",)], "h string"), "h", suffix.rules(spark, private=False)).first()
    assert public["domain"] == "example.net"


def test_links_of_broken_html(spark):
    page = "<A HREF='/x'>a<a href=/y rel=nofollow>b<!-- <a href='/no'> --><script>'<a href=\"/no\">'</script><p><a class=c href=\"/z?a=1&amp;b\">"
    found = spark.createDataFrame([(page,), (None,), ("",)], "h string").select(html.links("h").alias("l")).collect()
    assert [(x["href"], x["nofollow"]) for x in found[0]["l"]] == [("/x", False), ("/y", True), ("/z?a=1&b", False)]
    assert not found[1]["l"] and found[2]["l"] == []


def test_robots(spark):
    rules = spark.createDataFrame(robots.parse("User-agent: a\nUser-agent: b\nDisallow: /x\nAllow: /x/y$\nDisallow: /*.gif\n\nUser-agent: *\nDisallow: /\n", "h"), robots.RULES)
    asked = spark.createDataFrame([("h", p) for p in ("/x", "/x/y", "/x/yz", "/q.gif", "/q")] + [("other", "/x")], "host string, path string")
    got = {(r["host"], r["path"]): r["allowed"] for r in robots.allowed(asked, rules, "b").collect()}
    assert got == {("h", "/x"): False, ("h", "/x/y"): True, ("h", "/x/yz"): False, ("h", "/q.gif"): False, ("h", "/q"): True, ("other", "/x"): True}
    assert not any(r["allowed"] for r in robots.allowed(asked.filter("host = 'h'"), rules, "z").collect())


def test_filter_language():
    f = filters.parse("scheme_in(http) and (host_is(a) or not host_is(b)) xor true")
    assert f.text == "((scheme_in(http) and (host_is(a) or not host_is(b))) xor true)"
    with pytest.raises(ValueError):
        filters.parse("scheme_in(http) and")
    with pytest.raises(TypeError):
        UrlFilter.host_is("a") & ResponseFilter.status_in(200)


def test_bloom_is_the_sequential_one(spark):
    import hashlib

    rng = random.Random(3)
    keys = [rng.randrange(400) for _ in range(900)]
    bits, k, held, released = 512, 3, set(), set()
    for key in keys:
        h = hashlib.md5(str(key).encode()).hexdigest()
        a, b = int(h[:15], 16), int(h[15:30], 16) | 1
        places = {(a + i * b) % bits for i in range(k)}
        if not places <= held:
            released.add(key)
        held |= places
    df = spark.createDataFrame(list(enumerate(keys, 1)), "seq long, key long")
    assert {r["key"] for r in seen.bloom(df, bits, k).filter("released").collect()} == released


def test_once_batched_is_the_exact_set(spark):
    df = spark.createDataFrame([(i, i % 7) for i in range(1, 50)], "seq long, key long")
    got = {r["key"]: (r["flush"], r["release_seq"]) for r in seen.batched(df, 4).collect()}
    assert set(got) == set(range(7)) and got[1] == (1, 4) and got[0] == (2, 8)


def test_lru(spark):
    refs = [1, 2, 3, 1, 4, 2, 5, 1, 1]
    df = spark.createDataFrame(list(enumerate(refs, 1)), "seq long, key long")
    got = [r["hit"] for r in cache.exact_lru(df, 3).orderBy("seq").collect()]
    assert got == [False, False, False, True, False, False, False, False, True]


def _loop(rows, d_host, d_ip):
    """Always the permissible request that may go first, by instant and host."""
    waiting = {}
    for seq, host, arrive in rows:
        waiting.setdefault(host, []).append((seq, arrive))
    nxt, bay, out = dict.fromkeys(waiting, 0), -(10**18), {}
    while any(waiting.values()):
        start, host = min((max(bay, nxt[h], q[0][1]), h) for h, q in waiting.items() if q)
        seq, _ = waiting[host].pop(0)
        out[seq] = start
        bay, nxt[host] = start + d_ip, start + d_host
    return out


def test_schedule_is_the_loop(spark):
    rng = random.Random(5)
    rows = [(i, rng.randrange(5), rng.randrange(200)) for i in range(120)]
    df = spark.createDataFrame([(s, h, 0, a, 1) for s, h, a in rows], "seq long, host long, ip long, arrive_us long, latency_us long")
    got = lanes.schedule(df, 20, 3)
    assert {r["seq"]: r["start_us"] for r in got.collect()} == _loop(rows, 20, 3)
    assert tuple(lanes.violations(got, 20, 3).first())[:3] == (0, 0, 0)


def test_closed_form_is_the_loop(spark):
    rng = random.Random(6)
    rows = [(i, i % 3, i * 4 + rng.randrange(9)) for i in range(60)]
    df = spark.createDataFrame(rows, "seq long, host long, arrive_us long")
    last, want = {}, {}
    for s, h, a in rows:
        want[s] = last[h] = max(a, last.get(h, -(10**9)) + 25)
    assert {r["seq"]: r["start_us"] for r in lanes.starts(df, 25).collect()} == want


def test_threads_saturate():
    n = list(range(4000))
    rate = {t: fetchsim.simulate(n, n, [1000] * 4000, [1] * 4000, t, 30, 0, 0)["rate"] for t in (10, 20, 30, 60)}
    assert rate[20] == pytest.approx(2 * rate[10], rel=0.02) and rate[60] == pytest.approx(rate[30], rel=0.02)
    assert rate[30] == pytest.approx(fetchsim.law(30, 30, 1000, 10**9, 10**9, 0, 0), rel=0.02)


def test_delay_raises_what_is_held_not_the_rate():
    host = [k % 2000 for k in range(40_000)]
    runs = [fetchsim.simulate(host, host, [1000] * 40_000, [1] * 40_000, 8, 100, d, d, horizon=2_000_000) for d in (10_000, 20_000, 40_000)]
    assert runs[2]["rate"] == pytest.approx(runs[0]["rate"], rel=0.05)
    assert runs[1]["mean_delayed"] == pytest.approx(2 * runs[0]["mean_delayed"], rel=0.15) and runs[2]["mean_delayed"] == pytest.approx(4 * runs[0]["mean_delayed"], rel=0.15)


def test_feeder():
    assert feeder.next_target(11, 10, True) == 11 and feeder.next_target(9, 10, True) == 10 and feeder.next_target(30, 20, False) == 20
    assert feeder.quota(100, 30) == 3 and feeder.quota(1, 100) == 1


def test_ring_moves_only_to_the_new_shard(spark):
    a, b = ring.points(dict.fromkeys(range(4), 1), 50), ring.points(dict.fromkeys(range(5), 1), 50)

    def owner(points, h):
        return next((s for p, s in points if p >= h), points[0][1])

    for h in range(0, ring.SPACE, ring.SPACE // 500):
        assert owner(a, h) == owner(b, h) or owner(b, h) == 4


def test_spill_compaction_keeps_order(spark):
    log = spill.append(spark.createDataFrame([(i, i % 3) for i in range(30)], "seq long, host long"), buckets=1, segment=4)
    live = spill.remaining(log, log.filter("pos < 20 and pos % 4 <> 0"))
    packed = spill.compact(live, 0.6, 4).orderBy("pos").collect()
    assert [r["pos"] for r in packed] == list(range(15)) and [r["seq"] for r in packed] == sorted(r["seq"] for r in packed)


def _graph(spark, arcs, n):
    return spark.createDataFrame(arcs, "src long, dst long"), spark.createDataFrame([(i,) for i in range(n)], "id long")


GRAPHS = [([(0, 1), (1, 2), (2, 0), (2, 3)], 5), ([(i, 0) for i in range(1, 6)], 6), ([(0, 1), (1, 0), (2, 3)], 4), ([(0, 1)], 1 + 1)]


@pytest.mark.parametrize(("arcs", "n"), GRAPHS)
def test_centralities(spark, arcs, n):
    edges, nodes = _graph(spark, arcs, n)
    far = [[math.inf] * n for _ in range(n)]
    for i in range(n):
        far[i][i] = 0
    for a, b in arcs:
        far[a][b] = min(far[a][b], 1)
    for k, i, j in itertools.product(range(n), repeat=3):
        far[i][j] = min(far[i][j], far[i][k] + far[k][j])
    want = [sum(1 / far[y][x] for y in range(n) if y != x and far[y][x] < math.inf) for x in range(n)]
    got = {r["id"]: r["harmonic"] for r in centrality.harmonic_exact(edges, nodes).collect()}
    assert [got[i] for i in range(n)] == pytest.approx(want)
    sketch = {r["id"]: r["harmonic"] for r in centrality.harmonic_sketch(edges, nodes)[0].collect()}
    assert [sketch[i] for i in range(n)] == pytest.approx(want, abs=0.05)
    m = np.zeros((n, n))
    for a, b in arcs:
        m[b, a] += 1 / sum(x == a for x, _ in arcs)
    p = np.full(n, 1 / n)
    hang = np.array([not any(x == i for x, _ in arcs) for i in range(n)])
    for _ in range(8):
        p = 0.85 * (m @ p + p[hang].sum() / n) + 0.15 / n
    ranks = {r["id"]: r["rank"] for r in centrality.pagerank(edges, nodes, iterations=8).collect()}
    assert [ranks[i] for i in range(n)] == pytest.approx(p.tolist())


def test_degrees_of_an_empty_graph(spark):
    edges, nodes = spark.createDataFrame([], "src long, dst long"), spark.createDataFrame([(0,), (1,)], "id long")
    assert [tuple(r) for r in graph.degree_freq(edges, nodes).collect()] == [(0, 2)]
    assert graph.bfs(edges, nodes.limit(1)).count() == 1


def test_power_law_is_found_and_refused():
    rng = np.random.default_rng(1)
    x, f = np.unique(powerlaw._draw(rng, 2.5, 5, 10_000, 3000), return_counts=True)
    alpha, xmin, ks, _ = powerlaw.fit_histogram(x, f)
    assert abs(alpha - 2.5) < 0.15 and ks < 0.03
    x, f = np.unique(rng.geometric(0.1, 10_000), return_counts=True)
    assert powerlaw.fit_histogram(x, f)[2] > ks


def test_digests_ignore_what_changes(spark):
    from webgather.functions import digests

    pages = [f'<p class="{c}">Visits: {n} on {d} text {w}</p>' for c, n, d, w in (("a", 1, "3 May 2020", "x"), ("b", 22, "14 août 1999", "x"), ("c", 3, "1 Montag", "y"))]
    got = [r["d"] for r in spark.createDataFrame(list(enumerate(pages)), "i int, h string").orderBy("i").select(digests.digest("h").alias("d")).collect()]
    assert got[0] == got[1] != got[2]


def test_jaccard_links_against_all_pairs(spark):
    rng = random.Random(8)
    base = [" ".join(rng.choice("abcdefgh") * 3 + str(rng.randrange(30)) for _ in range(30)) for _ in range(6)]
    texts = base + [t.replace(t.split()[k], "new", 1) for t in base for k in (3, 20)] + [base[0], "", "one two"]
    sets = [{tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if (w := t.split()) else set() for t in texts]
    df = spark.createDataFrame(list(enumerate(texts)), "id long, t string")
    links, members = dedup.jaccard_pairs(df, "id", "t")
    rep = {r["id"]: r["rep"] for r in members.collect()}
    want = {(a, b) for a in range(len(texts)) for b in range(a + 1, len(texts)) if sets[a] and sets[b] and rep[a] == a and rep[b] == b and 100 * len(sets[a] & sets[b]) >= 75 * len(sets[a] | sets[b])}
    assert {(r["a"], r["b"]) for r in links.collect()} == want and rep[18] == 0


def test_gathering_with_caps(spark):
    nodes = spark.createDataFrame([(i, "h" + str(i % 3), i % 2) for i in range(30)], "id long, host string, ip int")
    edges = spark.createDataFrame([(i, j) for i in range(30) for j in ((i * 2 + 1) % 30, (i + 7) % 30)], "src long, dst long")
    log = crawl.gather(edges, nodes, spark.createDataFrame([(0,)], "id long"), crawl.Config(per_host=1, per_ip=2, cap=4)).toPandas()
    assert log["id"].is_unique and (log.groupby("host").size() <= 4).all() and (log.groupby(["round", "host"]).size() <= 1).all()


def gathered_in_turn(edges, nodes, seed, c):
    """{id: (depth, round, found, place among what the round found)} by lists, one page after the other."""
    of = {i: (h, p) for i, h, p in nodes}
    waiting, depth, place, done, cited, log = [seed], {seed: 0}, {seed: (0, 1)}, {}, {}, {}
    by = (lambda i: i) if c.order == ("id",) else place.get
    r = 0
    while waiting and len(log) < c.budget and (c.rounds is None or r < c.rounds):
        r += 1
        lanes, bays = {}, {}
        for i in sorted(waiting, key=by):
            lanes.setdefault(of[i][0], []).append(i)
        ready = []
        for h, lane in lanes.items():
            ready += list(enumerate(lane[: max(0, min(c.per_host, c.cap - done.get(h, 0)))]))
        for _, i in sorted(ready, key=lambda w: (w[0], by(w[1]))):
            bays.setdefault(of[i][1], []).append(i)
        ready = sorted((i for bay in bays.values() for i in bay[: c.per_ip]), key=lambda i: (-cited.get(i, 0) if c.priority == "indegree" else 0, by(i)))
        released = ready[: c.per_round]
        if not released:
            break
        new = {}
        for i in sorted(released, key=place.get):
            log[i] = (depth[i], r, *place[i])
            done[of[i][0]] = done.get(of[i][0], 0) + 1
            for a, b, _ in sorted((e for e in edges if e[0] == i), key=lambda e: e[2]):
                cited[b] = cited.get(b, 0) + 1
                if b not in depth:
                    new[b] = min(new.get(b, 1 << 30), depth[i] + 1)
        depth |= new
        place |= {b: (r, k + 1) for k, b in enumerate(new)}
        waiting = [i for i in waiting if i not in log] + list(new)
    return log


@pytest.mark.parametrize("config", [crawl.Config(2, 3), crawl.Config(1, 2, cap=4), crawl.Config(2, 3, order=("id",)), crawl.Config(per_round=5, priority="indegree", budget=30), crawl.Config(1, 2, rounds=5)])
def test_gathering_is_the_loop(spark, config):
    rng = random.Random(11)
    nodes = [(i, "h" + str(min(i % 7, 3)), i % 5 % 3) for i in range(48)]
    arcs = sorted({(rng.randrange(48), rng.randrange(48) if rng.random() < 0.6 else rng.randrange(6)) for _ in range(150)})
    edges = [(a, b, p) for (a, b), p in zip(arcs, rng.sample(range(len(arcs)), len(arcs)), strict=True)]
    log = crawl.gather(spark.createDataFrame(edges, "src long, dst long, pos long"), spark.createDataFrame(nodes, "id long, host string, ip int"), spark.createDataFrame([(0,)], "id long"), config)
    rows, want = log.collect(), gathered_in_turn(edges, nodes, 0, config)
    assert {x["id"]: (x["depth"], x["round"], x["found"], x["seq"]) for x in rows} == want
    if config.order != ("id",) and config.priority == "discovery":
        hosts, heads = {i: h for i, h, _ in nodes}, 0
        for r in range(1, 1 + max(x[1] for x in want.values())):
            heads += len({hosts[i] for i, x in want.items() if x[2] < r <= x[1]})
        assert tuple(crawl.heads_examined(log).first()) == (heads, len(want))


def test_places_moved(spark):
    """Three pages of depth 1, the least of them fetched last."""
    form = "id long, host string, depth int, found int, seq long, round int"
    rows = [(0, "a", 0, 0, 0, 1), (1, "b", 1, 1, 1, 3), (2, "c", 1, 1, 2, 2), (3, "d", 1, 1, 3, 2)]
    ideal = [(*x[:5], 1 + x[2]) for x in rows]
    got = crawl.deviation(spark.createDataFrame(rows, form), spark.createDataFrame(ideal, form)).first()
    assert (got["fetched"], got["mean_moved"], got["most_moved"], got["most_late"]) == (4, 1.0, 2, 1)


def test_running_sums(spark):
    from webgather.operators.sequence import running

    rng = random.Random(4)
    rows = [(i, rng.choice([None, 1, 5, 40])) for i in range(500)]
    got = {x["i"]: x["total"] for x in running(spark.createDataFrame(rng.sample(rows, 500), "i long, v long"), ["i"], "v", "total", 7).collect()}
    assert got == dict(zip(range(500), itertools.accumulate(v or 0 for _, v in rows), strict=True))
    assert running(spark.createDataFrame([], "i long, v long"), ["i"], "v", "total").count() == 0


def test_plans(spark):
    from helpers import SMALL

    from webgather.plans import web

    text = web.url_parts(spark, SMALL)._jdf.queryExecution().toString()
    assert "html" not in text.split("== Physical Plan ==")[1]
