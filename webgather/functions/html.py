"""Links, text and titles of HTML, as column expressions, and by a real parser as a check.

One module serves gathering and analysis: links found at one time are those found at the other.
"""

from __future__ import annotations

from html.parser import HTMLParser

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from webgather.functions import urls

HIDDEN = r"(?is)<(?:script\b.*?</script\s*>|style\b.*?</style\s*>|!--.*?-->)"
ANCHOR = r"""(?is)<a\s[^>]*?href\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'>]+))[^>]*>"""
BASE = r"""(?is)<base\s[^>]*?href\s*=\s*["']?([^"'\s>]+)"""


def visible(html: Column | str) -> Column:
    return F.regexp_replace(html, HIDDEN, " ")


def anchors(html: Column | str) -> Column:
    """The anchor tags with an href, in order."""
    return F.regexp_extract_all(visible(html), F.lit(ANCHOR), F.lit(0))


def href(tag: Column) -> Column:
    raw = F.concat(*(F.regexp_extract(tag, ANCHOR, k) for k in (1, 2, 3)))
    return F.replace(raw, F.lit("&amp;"), F.lit("&"))


def links(html: Column | str, follow_all: bool = True) -> Column:
    """An array of (pos from 1, href, nofollow)."""
    found = F.transform(anchors(html), lambda t, i: F.struct((i + 1).alias("pos"), href(t).alias("href"), t.rlike(r"(?i)\brel\s*=\s*[\"']?[^\"'>]*nofollow").alias("nofollow")))
    return found if follow_all else F.filter(found, lambda x: ~x["nofollow"])


def base_of(html: Column | str, url: Column | str) -> Column:
    own = F.regexp_extract(html, BASE, 1)
    return F.when(own != "", urls.resolve(url, own)).otherwise(F.col(url) if isinstance(url, str) else url)


def text(html: Column | str) -> Column:
    bare = F.regexp_replace(visible(html), r"(?s)<[^>]*>", " ")
    for name, char in (("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "'"), ("&nbsp;", " "), ("&amp;", "&")):
        bare = F.replace(bare, F.lit(name), F.lit(char))
    return F.trim(F.regexp_replace(bare, r"\s+", " "))


def title(html: Column | str) -> Column:
    return F.trim(F.regexp_replace(F.regexp_extract(html, r"(?is)<title[^>]*>(.*?)</title", 1), r"\s+", " "))


def exploded_links(pages: DataFrame, follow_all: bool = True) -> DataFrame:
    """page_id, pos, href, target (resolved) of every link."""
    return (
        pages.select("page_id", "url", base_of("html", "url").alias("base"), F.explode(links("html", follow_all)).alias("l"))
        .select("page_id", "url", F.col("l.pos").alias("pos"), F.col("l.href").alias("href"), urls.resolve("base", F.col("l.href")).alias("target"))
    )


class _Anchors(HTMLParser):
    def __init__(self):
        super().__init__()
        self.found: list[str] = []

    def handle_starttag(self, tag, attrs):
        if tag == "a":
            for k, v in attrs:
                if k == "href" and v is not None:
                    self.found.append(v)
                    break


def parsed_links(pages: DataFrame) -> DataFrame:
    """page_id, pos, href by the standard library's parser, a batch at a time."""

    def parse(batches):
        for batch in batches:
            ids, pos, hrefs = [], [], []
            for page, html in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                p = _Anchors()
                p.feed(html or "")
                p.close()
                ids += [page] * len(p.found)
                pos += range(1, len(p.found) + 1)
                hrefs += p.found
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(pos, pa.int32()), pa.array(hrefs, pa.string())], names=["page_id", "pos", "href"])

    return pages.select("page_id", "html").mapInArrow(parse, "page_id long, pos int, href string")


def consistency(pages: DataFrame) -> DataFrame:
    """Links that one of the two parsers finds and the other doesn't."""
    one = pages.select("page_id", F.explode(links("html")).alias("l")).select("page_id", F.col("l.pos").cast("int").alias("pos"), F.col("l.href").alias("href"))
    two = parsed_links(pages)
    return one.exceptAll(two).withColumn("side", F.lit("expression")).unionByName(two.exceptAll(one).withColumn("side", F.lit("parser")))
