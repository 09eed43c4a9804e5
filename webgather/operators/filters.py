"""Boolean filters over URLs and responses, as columns that Catalyst simplifies and pushes down."""

from __future__ import annotations

import re
from collections.abc import Callable, Sequence
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from webgather.functions import urls


@dataclass(frozen=True)
class Filter:
    """base: url or response; text: how it is written; make: its column."""

    base: str
    text: str
    make: Callable[[], Column]

    def _with(self, other: Filter, sign: str, f: Callable[[Column, Column], Column]) -> Filter:
        if {self.base, other.base} == {"url", "response"}:
            raise TypeError(f"{self.text} is over {self.base}, {other.text} over {other.base}")
        base = self.base if self.base != "any" else other.base
        return Filter(base, f"({self.text} {sign} {other.text})", lambda: f(self.make(), other.make()))

    def __and__(self, other):
        return self._with(other, "and", lambda a, b: a & b)

    def __or__(self, other):
        return self._with(other, "or", lambda a, b: a | b)

    def __xor__(self, other):
        return self._with(other, "xor", lambda a, b: a != b)

    def __invert__(self):
        return Filter(self.base, f"not {self.text}", lambda: ~self.make())

    def apply(self, df: DataFrame) -> DataFrame:
        return df.filter(self.make())


TRUE, FALSE = (Filter("any", str(v).lower(), lambda v=v: F.lit(v)) for v in (True, False))


class UrlFilter:
    """Predicates over a column `url`."""

    @staticmethod
    def _of(name: str, args: Sequence, f: Callable[[Column], Column]) -> Filter:
        return Filter("url", f"{name}({', '.join(map(str, args))})", lambda: f(F.col("url")))

    @classmethod
    def scheme_in(cls, *schemes: str) -> Filter:
        return cls._of("scheme_in", schemes, lambda u: urls.scheme(u).isin(*schemes))

    @classmethod
    def host_is(cls, name: str) -> Filter:
        return cls._of("host_is", [name], lambda u: urls.host(u) == name)

    @classmethod
    def domain_in(cls, *suffixes: str) -> Filter:
        def test(u: Column) -> Column:
            out = F.lit(False)
            for s in suffixes:
                out = out | (urls.host(u) == s) | urls.host(u).endswith("." + s)
            return out

        return cls._of("domain_in", suffixes, test)

    @classmethod
    def path_like(cls, pattern: str) -> Filter:
        return cls._of("path_like", [pattern], lambda u: urls.path(u).rlike(pattern))

    @classmethod
    def extension_in(cls, *names: str) -> Filter:
        return cls._of("extension_in", names, lambda u: F.lower(F.regexp_extract(urls.path(u), r"\.([A-Za-z0-9]+)$", 1)).isin(*names))

    @classmethod
    def longer_than(cls, n: str | int) -> Filter:
        return cls._of("longer_than", [n], lambda u: F.length(u) > int(n))

    @classmethod
    def deeper_than(cls, n: str | int) -> Filter:
        return cls._of("deeper_than", [n], lambda u: F.size(F.filter(F.split(urls.path(u), "/"), lambda s: s != "")) > int(n))

    @classmethod
    def has_param(cls, name: str) -> Filter:
        return cls._of("has_param", [name], lambda u: F.exists(F.split(urls.query(u), "&"), lambda p: F.substring_index(p, "=", 1) == name))

    @classmethod
    def repeats_segment(cls, times: str | int) -> Filter:
        def test(u: Column) -> Column:
            parts = F.filter(F.split(urls.path(u), "/"), lambda s: s != "")
            return F.coalesce(F.array_max(F.transform(parts, lambda s: F.size(F.filter(parts, lambda t: t == s)))), F.lit(0)) >= int(times)

        return cls._of("repeats_segment", [times], test)


class ResponseFilter:
    """Predicates over columns status, content_type, length, body."""

    @classmethod
    def status_in(cls, *codes: str | int) -> Filter:
        return Filter("response", f"status_in({', '.join(map(str, codes))})", lambda: F.col("status").isin(*map(int, codes)))

    @classmethod
    def type_is(cls, name: str) -> Filter:
        return Filter("response", f"type_is({name})", lambda: F.col("content_type") == name)

    @classmethod
    def length_between(cls, low: str | int, high: str | int) -> Filter:
        return Filter("response", f"length_between({low}, {high})", lambda: F.col("length").between(int(low), int(high)))

    @classmethod
    def body_like(cls, pattern: str) -> Filter:
        return Filter("response", f"body_like({pattern})", lambda: F.col("body").rlike(pattern))


KNOWN = {n: getattr(c, n) for c in (UrlFilter, ResponseFilter) for n in vars(c) if not n.startswith("_")}
TOKEN = re.compile(r"\s*(?:(\w+)\(([^()]*)\)|(\w+)|([()]))")


def parse(text: str) -> Filter:
    """A filter from text: names with arguments, true, false, not, and, xor, or (in falling rank), and brackets."""
    tokens, at = [], 0
    while at < len(text.rstrip()):
        m = TOKEN.match(text, at)
        if not m:
            raise ValueError(f"can't read a filter at {text[at : at + 20]!r}")
        tokens.append(m)
        at = m.end()
    tokens.reverse()

    def word() -> str:
        return (tokens[-1][3] or tokens[-1][4] or "") if tokens else ""

    def one() -> Filter:
        if not tokens:
            raise ValueError("a filter ends early")
        m = tokens.pop()
        if m[1]:
            if m[1] not in KNOWN:
                raise ValueError(f"no filter is named {m[1]}")
            return KNOWN[m[1]](*(a.strip() for a in m[2].split(",") if a.strip()))
        if m[3] == "not":
            return ~one()
        if m[3] in ("true", "false"):
            return TRUE if m[3] == "true" else FALSE
        if m[4] == "(":
            inner = rank(0)
            if word() != ")":
                raise ValueError("a bracket isn't closed")
            tokens.pop()
            return inner
        raise ValueError(f"{m[0].strip()!r} is out of place")

    signs = [("or", lambda a, b: a | b), ("xor", lambda a, b: a ^ b), ("and", lambda a, b: a & b)]

    def rank(k: int) -> Filter:
        if k == len(signs):
            return one()
        out = rank(k + 1)
        while word() == signs[k][0]:
            tokens.pop()
            out = signs[k][1](out, rank(k + 1))
        return out

    found = rank(0)
    if tokens:
        raise ValueError(f"{tokens[-1][0].strip()!r} is left over")
    return found


@dataclass(frozen=True)
class Pipeline:
    """The five points at which a filter decides; a row counts at a point if it passed all before."""

    schedule: Filter = TRUE
    fetch: Filter = TRUE
    parse: Filter = TRUE
    follow: Filter = TRUE
    store: Filter = TRUE

    def apply(self, df: DataFrame) -> DataFrame:
        ok = F.lit(True)
        for stage in ("schedule", "fetch", "parse", "follow", "store"):
            ok = ok & F.coalesce(getattr(self, stage).make(), F.lit(False))
            df = df.withColumn(f"ok_{stage}", ok)
        return df

    def counts(self, df: DataFrame) -> DataFrame:
        return self.apply(df).agg(F.count(F.lit(1)).alias("n_input"), *(F.count_if(f"ok_{s}").alias(f"n_{s}") for s in ("schedule", "fetch", "parse", "follow", "store")))


def trap_guard(max_hops: int, max_depth: int, max_repeat: int) -> Filter:
    """Refuses long redirect chains (a column hops), deep paths and repeating segments."""
    return Filter("any", f"hops_over({max_hops})", lambda: ~(F.col("hops") > max_hops)) & ~UrlFilter.deeper_than(max_depth) & ~UrlFilter.repeats_segment(max_repeat)
