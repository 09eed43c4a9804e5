"""Personal data: fixed forms, and unseen identifiers found by contexts that bootstrap from them.

One pass over the texts finds the fixed forms (the seeds), other tokens that look like
identifiers (the loose ones), and the contexts of both: the word before, the two words before,
and the word after. The rest is SQL over these few: a graph of contexts and instances is scored
in rounds, a context by the share of its instances believed to be of a kind, an instance that
is no seed by the mean of its contexts. Loose tokens next to a context that is scored high and
that several different seeds support become spans of that kind.

Defined cases: a null text is empty and has no spans; rows with one id, and equal rows, stay
apart; equal spans are reported once a row; an empty table gives an empty result; other columns
are ignored.
"""

from __future__ import annotations

import re

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from webgather.llm._shared import joined, written

KINDS = ("email", "ip", "card", "phone")
EMAIL = re.compile(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
IP = re.compile(r"[0-9]+(?:\.[0-9]+)(?:\.[0-9]+)(?:\.[0-9]+)")
CARD = re.compile(r"[0-9](?:[ -]?[0-9])+")
PHONE = re.compile(r"\+[0-9][ ().0-9-]+[0-9]")
#: Tokens that look like identifiers: an address with a spelt sign, or a number of seven digits or more with its marks.
LOOSE = re.compile(r"[A-Za-z0-9._%+-]+ ?(?:@|\(at\)|\[at\]) ?[A-Za-z0-9.-]+|\+?\(?[0-9](?:[ ().-]{0,2}[0-9]){5,}")
WORD = re.compile(r"[^\W\d_]+")
#: Characters looked at first for the words of a context; more are, where these cut a word or hold too few.
NEAR = 48

_ENTRY = "array<struct<kind:string,start:int,end:int,instance:string,contexts:array<string>>>"
SCHEMA = f"doc_id long, row long, seeds {_ENTRY}, loose {_ENTRY}"


def luhn(digits: str) -> bool:
    total = sum(map(int, digits[-1::-2]))
    return (total + sum(sum(divmod(2 * int(d), 10)) for d in digits[-2::-2])) % 10 == 0


def digits_of(s: str) -> str:
    return "".join(c for c in s if "0" <= c <= "9")


def _emails(text: str):
    """As EMAIL.finditer: the parts before each sign are what is tried, not every letter of the text."""
    at, low = text.find("@"), 0
    while at >= 0:
        a = at
        while a > low and (text[a - 1].isascii() and text[a - 1].isalnum() or text[a - 1] in "._%+-"):
            a -= 1
        m = EMAIL.match(text, a) if a < at else None
        if m:
            yield a, m.end()
            low = m.end()
        at = text.find("@", max(at + 1, low))


def base_spans(text: str) -> list[tuple[str, int, int]]:
    """The fixed forms, by kind and start."""
    out = [("email", a, b) for a, b in _emails(text)] if "@" in text else []
    out += [("ip", *m.span()) for m in IP.finditer(text) if all(int(p) <= 255 for p in m[0].split("."))] if "." in text else []
    for m in CARD.finditer(text):
        if m.end() - m.start() >= 13 and 13 <= len(d := digits_of(m[0])) <= 19 and luhn(d):
            out.append(("card", *m.span()))
    if "+" in text:
        out += [("phone", *m.span()) for m in PHONE.finditer(text) if 9 <= len(digits_of(m[0])) <= 15]
    return out


def _before(text: str, a: int) -> list[str]:
    """The last two words that end before a, whole."""
    near = NEAR
    while True:
        low = max(0, a - near)
        found = [m for m in WORD.finditer(text, low, a)][-2:]
        if low == 0 or (len(found) == 2 and found[0].start() > low):
            return [m[0].lower() for m in found]
        near *= 4


def _contexts(text: str, a: int, b: int) -> list[str]:
    before = _before(text, a)
    after = WORD.search(text, b)
    mark = text[max(0, a - 2) : a].strip()[-1:]
    mark = mark if mark in (":", "=", "#", "(") else ""
    out = [f"<{before[-1]}{mark}"] if before else []
    return out + ([f"<{before[0]} {before[1]}{mark}"] if len(before) > 1 else []) + ([f">{after[0].lower()}"] if after else [])


def _kinds_of(token: str) -> list[str]:
    if any(s in token for s in ("@", "(at)", "[at]")):
        return ["email"]
    n = len(digits_of(token))
    return (["ip"] if token.count(".") == 3 and n <= 12 else []) + (["card"] if 12 <= n <= 19 else []) + (["phone"] if 7 <= n <= 15 else [])


def _scan(batches):
    entry = pa.struct([("kind", pa.string()), ("start", pa.int32()), ("end", pa.int32()), ("instance", pa.string()), ("contexts", pa.list_(pa.string()))])
    for batch in batches:
        seeds, loose = [], []
        for text in batch.column(2):
            text = text.as_py() or ""
            base = base_spans(text)
            seeds.append([{"kind": k, "start": a, "end": b, "instance": text[a:b].lower() if k == "email" else digits_of(text[a:b]), "contexts": _contexts(text, a, b)} for k, a, b in base])
            taken = sorted((a, b) for _, a, b in base)
            own = []
            for m in LOOSE.finditer(text):
                a, b = m.span()
                if any(x < b and a < y for x, y in taken):
                    continue
                contexts = _contexts(text, a, b)
                own += [{"kind": k, "start": a, "end": b, "instance": m[0].lower() if k == "email" else digits_of(m[0]), "contexts": contexts} for k in _kinds_of(m[0])]
            loose.append(own)
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(seeds, pa.list_(entry)), pa.array(loose, pa.list_(entry))], names=["doc_id", "row", "seeds", "loose"])


def context_scores(found: DataFrame, rounds: int = 3, doubt: float = 2.0) -> DataFrame:
    """context, kind, belief (0 to 1), support (different seeds of the kind) from the scanned rows."""
    parts = [found.select(F.explode(c).alias("x"), F.lit(c == "seeds").alias("seed")).select("x.kind", "x.instance", "seed", F.explode("x.contexts").alias("context")) for c in ("seeds", "loose")]
    edges = written(parts[0].unionByName(parts[1]).groupBy("context", "instance", "kind", "seed").agg(F.count(F.lit(1)).alias("n")))
    # a loose token stands once for each kind it could be, and counts as one
    total = written(edges.groupBy("context", "instance", "seed").agg(F.max("n").alias("n")).groupBy("context").agg(F.sum("n").alias("total")))
    believed = edges.withColumn("belief", F.col("seed").cast("double"))
    for k in range(rounds):
        scored = believed.groupBy("context", "kind").agg(F.sum(F.col("n") * F.col("belief")).alias("b"), F.count_if("seed").alias("support"), F.count(F.lit(1)).alias("uses")).join(total, "context")
        scored = written(scored.select("context", "kind", (F.col("b") / (F.col("total") + doubt)).alias("belief"), "support", "uses"))
        if k + 1 < rounds:
            near = joined(edges, scored.select("context", "kind", F.col("belief").alias("c"), "uses"), ["context", "kind"], "uses")
            means = written(near.groupBy("instance", "kind").agg((F.sum(F.col("n") * F.col("c")) / F.sum("n")).alias("mean"), F.count(F.lit(1)).alias("places")))
            believed = joined(edges, means, ["instance", "kind"], "places").select("context", "instance", "kind", "seed", "n", F.when(F.col("seed"), 1.0).otherwise(F.col("mean")).alias("belief"))
    return scored


def find_personal_data(docs: DataFrame, belief: float = 0.8, support: int = 5, rounds: int = 3, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, seeds (array of kind, start, end), added (the same) for every row of docs; code points, end exclusive."""
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.monotonically_increasing_id().alias("row"), F.col(text_col).alias("body"))
    found = written(rows.mapInArrow(_scan, SCHEMA))
    trusted = context_scores(found, rounds).filter((F.col("belief") >= belief) & (F.col("support") >= support)).select("context", "kind", "belief")
    loose = found.select("row", F.explode("loose").alias("x")).select("row", "x.kind", "x.start", "x.end", F.explode("x.contexts").alias("context"))
    # how many loose tokens a trusted context has decides how it is joined
    trusted = written(trusted.join(loose.groupBy("context", "kind").agg(F.count(F.lit(1)).alias("met")), ["context", "kind"]))
    best = joined(loose, trusted, ["context", "kind"], "met").groupBy("row", "start", "end").agg(F.max_by("kind", F.struct("belief", "kind")).alias("kind"))
    added = best.groupBy("row").agg(F.array_sort(F.collect_list(F.struct("kind", "start", "end"))).alias("added"))
    bare = F.transform("seeds", lambda s: F.struct(s["kind"].alias("kind"), s["start"].alias("start"), s["end"].alias("end")))
    none = F.array().cast("array<struct<kind:string,start:int,end:int>>")
    return found.select("doc_id", "row", bare.alias("seeds")).join(added, "row", "left").select("doc_id", "seeds", F.coalesce("added", none).alias("added"))


def spelled(spans):
    """kind:start:end, by kind as in KINDS and then start, joined by commas."""
    rank = F.array(*(F.lit(k) for k in KINDS))
    keyed = F.array_sort(F.transform(spans, lambda s: F.struct(F.array_position(rank, s["kind"]), s["start"], s["end"], s["kind"].alias("kind"))))
    return F.array_join(F.transform(keyed, lambda s: F.concat_ws(":", s["kind"], s["start"], s["end"])), ",")
