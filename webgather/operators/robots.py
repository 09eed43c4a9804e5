"""Exclusion rules: parsing, and which URLs they allow."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

RULES = "host string, agent string, allow boolean, pattern string, delay_us long"


def parse(text: str, host: str = "") -> list[tuple]:
    """Rows of RULES from an exclusion file; agents that follow each other share the rules after them."""
    rows: list[tuple] = []
    agents: list[str] = []
    in_rules, delay = False, None
    for line in text.splitlines():
        key, sep, value = line.split("#")[0].partition(":")
        key, value = key.strip().lower(), value.strip()
        if not sep:
            continue
        if key == "user-agent":
            agents = [] if in_rules else agents
            agents.append(value.lower())
            in_rules = False
        elif key in ("allow", "disallow") and agents:
            in_rules = True
            if value:
                rows += [(host, a, key == "allow", value, None) for a in agents]
        elif key == "crawl-delay" and agents:
            in_rules = True
            try:
                delay = int(float(value) * 1_000_000)
            except ValueError:
                continue
            rows += [(host, a, None, None, delay) for a in agents]
    return rows


def _regex(pattern):
    """A rule's pattern: * is anything, $ at the end ends the path, else it is a prefix."""
    quoted = F.regexp_replace(pattern, r"([.\\+?^()\[\]{}|])", r"\\$1")
    return F.concat(F.lit("^"), F.regexp_replace(F.regexp_replace(quoted, r"\*", ".*"), r"\$(?!$)", r"\\$"))


def allowed(requests: DataFrame, rules: DataFrame, agent: str = "*") -> DataFrame:
    """requests (with host and path) and allowed: the longest matching rule of the agent's group decides, allow on a tie."""
    own = rules.filter(F.lower("agent") == agent.lower()).select("host").distinct().withColumn("own", F.lit(True))
    group = rules.join(F.broadcast(own), "host", "left").filter(F.when(F.col("own"), F.lower("agent") == agent.lower()).otherwise(F.col("agent") == "*"))
    patterns = group.filter("pattern is not null").select("host", "allow", F.length("pattern").alias("n"), _regex(F.col("pattern")).alias("rx"))
    keyed = requests.withColumn("_row", F.monotonically_increasing_id())
    hits = keyed.select("_row", "host", "path").join(patterns, "host").filter("path rlike rx")
    verdict = hits.groupBy("_row").agg(F.max_by("allow", F.struct("n", "allow")).alias("allowed"))
    return keyed.join(verdict, "_row", "left").withColumn("allowed", F.coalesce("allowed", F.lit(True))).drop("_row")
