"""URL splitting, normal forms and resolution, as column expressions."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Groups: scheme, authority, path, query, fragment.
PATTERN = r"^(?:([A-Za-z][A-Za-z0-9+.\-]*):)?(?://([^/?#]*))?([^?#]*)(?:\?([^#]*))?(?:#((?s:.*)))?$"
#: Groups: user info, host, port.
AUTHORITY = r"^(?:(.*)@)?(\[[^\]]*\]|[^:]*)(?::([0-9]*))?$"
#: What needs no escape in a URL, by RFC 3986.
UNRESERVED = "A-Za-z0-9._~\\-"
RESERVED = ":/?#\\[\\]@!$&'()*+,;="
PIECES = f"%[0-9A-Fa-f]{{2}}|[{UNRESERVED}{RESERVED}]+|[^{UNRESERVED}{RESERVED}%]+|%"


def _part(url: Column | str, group: int) -> Column:
    return F.regexp_extract(url, PATTERN, group)


def scheme(url: Column | str) -> Column:
    return F.lower(_part(url, 1))


def authority(url: Column | str) -> Column:
    return _part(url, 2)


def host(url: Column | str) -> Column:
    return F.lower(F.regexp_extract(authority(url), AUTHORITY, 2))


def port(url: Column | str) -> Column:
    return F.regexp_extract(authority(url), AUTHORITY, 3)


def path(url: Column | str) -> Column:
    return _part(url, 3)


def query(url: Column | str) -> Column:
    return _part(url, 4)


def fragment(url: Column | str) -> Column:
    return _part(url, 5)


def split(url: Column | str) -> Column:
    """A struct of all parts; absent parts are empty strings, a null URL is null."""
    parts = {"scheme": scheme(url), "user_info": F.regexp_extract(authority(url), AUTHORITY, 1), "host": host(url), "port": port(url), "path": path(url), "query": query(url), "fragment": fragment(url)}
    return F.struct(*(c.alias(n) for n, c in parts.items()))


def unescape(text: Column, reserved_stay: bool = True) -> Column:
    """Escapes in upper case; those of unreserved characters undone; what a URL can't hold escaped."""
    code = lambda p: F.conv(F.substring(p, 2, 2), 16, 10).cast("int")
    plain = f"^[{UNRESERVED}]$" if reserved_stay else "^[!-~]$"

    def piece(p: Column) -> Column:
        is_escape = p.rlike("^%[0-9A-Fa-f]{2}$")
        char = F.when(is_escape & (code(p) < 128), F.char(code(p)))
        return (
            F.when(is_escape & char.rlike(plain), char)
            .when(is_escape, F.upper(p))
            .when(p == "%", "%25")
            .when(p.rlike(f"^[{UNRESERVED}{RESERVED}]+$"), p)
            .otherwise(F.regexp_replace(F.hex(p), "(..)", r"%$1"))
        )

    return F.array_join(F.transform(F.regexp_extract_all(text, F.lit(f"({PIECES})"), F.lit(1)), piece), "")


def without_dots(p: Column) -> Column:
    """A path with its . and .. segments resolved."""
    parts = F.split(p, "/")

    def step(stack: Column, s: Column) -> Column:
        return F.when(s == ".", stack).when(s == "..", F.when(F.size(stack) > 1, F.slice(stack, 1, F.size(stack) - 1)).otherwise(stack)).otherwise(F.concat(stack, F.array(s)))

    stack = F.aggregate(parts, F.array().cast("array<string>"), step)
    last = F.element_at(parts, -1)
    joined = F.array_join(stack, "/")
    joined = F.when(last.isin(".", ".."), F.concat(joined, F.lit("/"))).otherwise(joined)
    return F.when(p.contains("/.") | p.startswith("."), F.when(p.startswith("/") & ~joined.startswith("/"), F.concat(F.lit("/"), joined)).otherwise(joined)).otherwise(p)


def normalise(url: Column | str, drop_fragment: bool = True, sort_query: bool = False, drop_params: Sequence[str] = ()) -> Column:
    """The canonical form: lower-case scheme and host, no default port, no dot segments, escapes as in unescape."""
    u = F.col(url) if isinstance(url, str) else url
    s, h, n = scheme(u), host(u), port(u)
    user = F.regexp_extract(authority(u), AUTHORITY, 1)
    keep_port = (n != "") & ~(((s == "http") & (n == "80")) | ((s == "https") & (n == "443")))
    p = without_dots(unescape(path(u)))
    p = F.when((p == "") & (authority(u) != ""), "/").otherwise(p)
    q = unescape(query(u))
    if drop_params or sort_query:
        params = F.filter(F.split(q, "&"), lambda x: ~F.substring_index(x, "=", 1).isin(list(drop_params)) & (x != ""))
        q = F.array_join(F.array_sort(params) if sort_query else params, "&")
    tail = F.when(fragment(u) != "", F.concat(F.lit("#"), fragment(u))).otherwise("") if not drop_fragment else F.lit("")
    return F.concat(
        F.when(s != "", F.concat(s, F.lit(":"))).otherwise(""),
        F.when(h != "", F.concat(F.lit("//"), F.when(user != "", F.concat(user, F.lit("@"))).otherwise(""), h, F.when(keep_port, F.concat(F.lit(":"), n)).otherwise(""))).otherwise(""),
        p,
        F.when(q != "", F.concat(F.lit("?"), q)).otherwise(""),
        tail,
    )


def resolve(base: Column | str, href: Column | str) -> Column:
    """The absolute URL of a reference found on a page."""
    b, r = (F.col(x) if isinstance(x, str) else x for x in (base, href))
    r = F.trim(r)
    root = F.concat(scheme(b), F.lit("://"), authority(b))
    folder = F.regexp_extract(path(b), "^(.*/)", 1)
    folder = F.when(folder == "", "/").otherwise(folder)
    bare = F.concat(root, F.when(path(b) == "", "/").otherwise(path(b)))
    asked = F.when(query(b) != "", F.concat(F.lit("?"), query(b))).otherwise("")
    end = F.regexp_extract(r, r"^[^?#]*((?s:.*))$", 1)
    stem = F.regexp_extract(r, r"^([^?#]*)", 1)
    return (
        F.when(r == "", F.concat(bare, asked))
        .when(r.rlike("^[A-Za-z][A-Za-z0-9+.\\-]*:"), r)
        .when(r.startswith("//"), F.concat(scheme(b), F.lit(":"), r))
        .when(r.startswith("/"), F.concat(root, without_dots(stem), end))
        .when(r.startswith("?"), F.concat(bare, r))
        .when(r.startswith("#"), F.concat(bare, asked, r))
        .otherwise(F.concat(root, without_dots(F.concat(folder, stem)), end))
    )


def lane_key(url: Column | str) -> Column:
    """Scheme and authority: what names a host lane."""
    return F.concat(scheme(url), F.lit("://"), F.lower(authority(url)))


def remainder(url: Column | str) -> Column:
    """Path and query: what a lane holds of a URL."""
    return F.concat(F.when(path(url) == "", "/").otherwise(path(url)), F.when(query(url) != "", F.concat(F.lit("?"), query(url))).otherwise(""))
