"""Host lanes, address bays and polite schedules.

Requests have a host, an ip, an order within the host and an arrival in microseconds. One
delay level has a closed form in windows; both together run as an event loop in each ip.
"""

from __future__ import annotations

import heapq
from collections.abc import Sequence

import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

SCHEDULE = "seq long, host long, ip long, arrive_us long, latency_us long, start_us long"


def build(df: DataFrame, host: str, order: Sequence[str]) -> DataFrame:
    """df with pos, the 1-based place in the host's lane."""
    return df.withColumn("pos", F.row_number().over(Window.partitionBy(host).orderBy(*order)))


def starts(df: DataFrame, delay_us: int | Column, host: str = "host", arrive: str = "arrive_us", order: str = "seq", measure_from: str = "start", latency: str = "latency_us") -> DataFrame:
    """df with start_us: the earliest polite start of each request of a lane.

    From start to start, start_i is i * d + max over j <= i of (arrive_j - j * d). From end to
    start, what lies between the starts is the latency and the delay, and their sums take i * d's place.
    """
    w = Window.partitionBy(host).orderBy(order)
    upto = w.rowsBetween(Window.unboundedPreceding, 0)
    d = F.lit(delay_us) if isinstance(delay_us, int) else delay_us
    if measure_from == "start":
        passed = F.row_number().over(w) * d
    else:
        passed = F.coalesce(F.sum(F.col(latency) + d).over(w.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    rows = df.withColumn("_s", passed)
    return rows.withColumn("start_us", F.col("_s") + F.max(F.col(arrive) - F.col("_s")).over(upto)).drop("_s")


def bays(lanes: DataFrame) -> DataFrame:
    """ip, priority, host: of each bay the lane to take next; lanes: ip, bay_next_us, host, next_us (not empty)."""
    best = F.min(F.struct(F.col("next_us"), F.col("host"))).alias("b")
    return lanes.groupBy("ip", "bay_next_us").agg(best).select("ip", F.greatest("bay_next_us", "b.next_us").alias("priority"), F.col("b.host").alias("host"))


def peek(bays_: DataFrame, now_us: int) -> DataFrame:
    """The head of the frontier, and how long until it may be released (0: now)."""
    return bays_.orderBy("priority", "ip", "host").limit(1).select("ip", "host", "priority", F.greatest(F.col("priority") - now_us, F.lit(0)).alias("wait_us"))


def _event_loop(pdf: pd.DataFrame, d_host: int, d_ip: int, from_end: bool, keepalive_us: int) -> list[int]:
    """Starts of one ip's requests: always the lane that may go first, ties to the lesser host."""
    lanes: dict[int, list[int]] = {}
    for k, host in enumerate(pdf["host"].tolist()):
        lanes.setdefault(host, []).append(k)
    arrive, latency = pdf["arrive_us"].tolist(), pdf["latency_us"].tolist()
    own_host = pdf["d_host"].tolist() if "d_host" in pdf else None
    at = dict.fromkeys(lanes, 0)
    heap = [(arrive[q[0]], host) for host, q in lanes.items()]
    heapq.heapify(heap)
    out, bay = [0] * len(pdf), -(1 << 62)
    ready: list[int] = []
    while heap or ready:
        # lanes that may go before the bay does are all alike to it: the lesser host is next
        while heap and heap[0][0] <= bay:
            heapq.heappush(ready, heapq.heappop(heap)[1])
        if ready:
            host, start = heapq.heappop(ready), bay
        else:
            when, host = heapq.heappop(heap)
            start = max(when, bay)
        queue = lanes[host]
        used = 0
        while True:
            k = queue[at[host]]
            out[k] = start
            at[host] += 1
            used += latency[k]
            end = start + (latency[k] if from_end else 0)
            if not keepalive_us or at[host] == len(queue) or used + latency[queue[at[host]]] > keepalive_us or arrive[queue[at[host]]] > start + latency[k]:
                break
            start += latency[k]
        bay = end + d_ip
        if at[host] < len(queue):
            heapq.heappush(heap, (max(end + (own_host[k] if own_host else d_host), arrive[queue[at[host]]]), host))
    return out


def schedule(df: DataFrame, d_host_us: int, d_ip_us: int, measure_from: str = "start", keepalive_us: int = 0, per_host: DataFrame | None = None) -> DataFrame:
    """SCHEDULE rows: starts under both delays. per_host: (host, d_host) for hosts with a delay of their own.

    Bays share nothing, so ips run in parallel; an ip's requests must fit one task.
    """
    rows = df.select("seq", F.col("host").cast("long").alias("host"), F.col("ip").cast("long").alias("ip"), "arrive_us", "latency_us")
    if per_host is not None:
        rows = rows.join(per_host, "host", "left").withColumn("d_host", F.coalesce("d_host", F.lit(d_host_us)))

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(["host", "seq"])
        return pdf[["seq", "host", "ip", "arrive_us", "latency_us"]].assign(start_us=_event_loop(pdf, d_host_us, d_ip_us, measure_from == "end", keepalive_us))

    return rows.groupBy("ip").applyInPandas(run, SCHEDULE)


def violations(scheduled: DataFrame, d_host_us: int, d_ip_us: int) -> DataFrame:
    """Gaps under the delay per host and per ip, and rows out of their lane's order: all zero in a polite schedule."""
    gap = lambda by: F.col("start_us") - F.lag("start_us").over(Window.partitionBy(by).orderBy("start_us", "seq"))
    fifo = F.lag("start_us").over(Window.partitionBy("host").orderBy("seq"))
    rows = scheduled.select((gap("host") < d_host_us).alias("h"), (gap("ip") < d_ip_us).alias("i"), (fifo > F.col("start_us")).alias("o"), (F.col("start_us") < F.col("arrive_us")).alias("e"))
    return rows.agg(F.count_if("h").alias("host_gaps"), F.count_if("i").alias("ip_gaps"), F.count_if("o").alias("out_of_order"), F.count_if("e").alias("too_early"))


def overlaps(scheduled: DataFrame, by: str = "ip") -> DataFrame:
    """Fetches of a bay that begin before an earlier one has ended."""
    end = F.max(F.col("start_us") + F.col("latency_us")).over(Window.partitionBy(by).orderBy("start_us", "seq").rowsBetween(Window.unboundedPreceding, -1))
    return scheduled.select((end > F.col("start_us")).alias("o")).agg(F.count_if("o").alias("overlaps"), F.count(F.lit(1)).alias("fetches"))


def front(scheduled: DataFrame, grid_us: int) -> DataFrame:
    """slot, ready: of each grid instant, how many requests have come and not yet begun."""
    slot = lambda c: F.ceil(F.col(c) / grid_us)
    steps = scheduled.select(slot("arrive_us").alias("slot"), F.lit(1).alias("d")).unionByName(scheduled.select(slot("start_us").alias("slot"), F.lit(-1).alias("d")))
    per = steps.groupBy("slot").agg(F.sum("d").alias("d"))
    return per.select("slot", F.sum("d").over(Window.orderBy("slot")).alias("ready"))


def ready_inversions(scheduled: DataFrame, lag: int) -> DataFrame:
    """A hand-over list that fetchers take from in the order of release; how often a lane of it would by then rank lower."""
    rows = scheduled.select("ip", "seq", "start_us", (F.col("start_us") - F.col("arrive_us")).alias("waited"))
    later = F.lead("waited", lag).over(Window.partitionBy("ip").orderBy("start_us", "seq"))
    return rows.select((later > F.col("waited")).alias("x")).agg(F.count(F.lit(1)).alias("released"), F.count_if("x").alias("inversions"))


def adaptive_delay(latency: Column, factor: float, least_us: int, most_us: int, branching: Column | None = None) -> Column:
    """A delay from the last download's time, and, where given, from how many links a page of the site yields."""
    d = latency * factor
    if branching is not None:
        d = d / F.greatest(F.lit(1.0), F.log2(branching + 1))
    return F.least(F.greatest(d.cast("long"), F.lit(least_us)), F.lit(most_us))


def two_queue_checks(pdf: pd.DataFrame, delay_us: int) -> tuple[int, int]:
    """(heads looked at, releases) of a plain ready queue whose early heads go to the back again."""
    queue = [(int(a), int(h)) for a, h in zip(pdf["arrive_us"], pdf["host"], strict=True)]
    next_at: dict[int, int] = {}
    now = checks = done = 0
    while queue:
        left = []
        for arrive, host in queue:
            checks += 1
            if max(arrive, next_at.get(host, 0)) <= now:
                next_at[host] = now + delay_us
                done += 1
            else:
                left.append((arrive, host))
        queue = left
        if queue:
            now = min(max(a, next_at.get(h, 0)) for a, h in queue)
    return checks, done
