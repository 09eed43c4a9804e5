"""Digests of content that ignore what changes between copies of a page."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Names of months and days in English, French, German and Spanish.
MONTHS_AND_DAYS = (
    "january february march april may june july august september october november december "
    "monday tuesday wednesday thursday friday saturday sunday "
    "janvier février mars avril mai juin juillet août septembre octobre novembre décembre "
    "lundi mardi mercredi jeudi vendredi samedi dimanche "
    "januar februar märz juni juli oktober dezember montag dienstag mittwoch donnerstag freitag samstag sonntag "
    "enero febrero marzo abril mayo junio julio agosto septiembre octubre noviembre diciembre "
    "lunes martes miércoles jueves viernes sábado domingo"
).split()
NAMES = r"(?i)(^|[^a-zà-ÿ])(" + "|".join(sorted(set(MONTHS_AND_DAYS), key=lambda w: (-len(w), w))) + r")($|[^a-zà-ÿ])"
TAG = r"(?s)<(/?[A-Za-z][A-Za-z0-9]*)[^>]*>"
ARTICLE = r"(?is)<article[^>]*>(.*?)</article>"


def scoped(html: Column | str, scope: str) -> Column:
    return F.regexp_extract(html, ARTICLE, 1) if scope == "article" else (F.col(html) if isinstance(html, str) else html)


def reduced(content: Column, attributes: bool = True, digits: bool = True, dates: bool = True) -> Column:
    """The content without what is named: tags' attributes, digits, names of months and days."""
    if attributes:
        content = F.regexp_replace(content, TAG, r"<$1>")
    if dates:
        content = F.regexp_replace(content, NAMES, r"$1$3")
    if digits:
        content = F.regexp_replace(content, r"[0-9]+", "")
    return content


def digest(content: Column | str, mode: str = "summary", scope: str = "page") -> Column:
    """raw, summary, or a set of parts joined by +: attributes, digits, dates."""
    c = scoped(content, scope)
    if mode == "raw":
        return F.md5(c)
    parts = {"attributes", "digits", "dates"} if mode == "summary" else set(mode.split("+"))
    return F.md5(reduced(c, *(p in parts for p in ("attributes", "digits", "dates"))))
