"""Distances and centralities: exact by levels from all sources, by sketches, and PageRank."""

from __future__ import annotations

from itertools import count

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from webgather.operators import reach
from webgather.operators.graph import step_table


def distances(edges: DataFrame, sources: DataFrame, most: int | None = None, every: int = 8) -> DataFrame:
    """source, node, d: from each source (id) along the edges, up to `most` if it is set. The pair table is the size of the answer."""
    reached = step_table(sources.select(F.col("id").alias("source"), F.col("id").alias("node"), F.lit(0).alias("d")))
    border, d, parts = reached, 0, 0
    while most is None or d < most:
        d += 1
        new = border.join(edges, border.node == edges.src).select("source", F.col("dst").alias("node")).distinct().join(reached, ["source", "node"], "left_anti").select("source", "node", F.lit(d).alias("d"))
        border = step_table(new)
        if border.isEmpty():
            break
        reached, parts = reached.unionByName(border), parts + 1
        if parts % every == 0:
            reached = step_table(reached)
    return reached


def distribution(pairs: DataFrame) -> DataFrame:
    """d, pairs: ordered pairs at that distance, a node and itself at 0."""
    return pairs.groupBy("d").agg(F.count(F.lit(1)).alias("pairs"))


def spread(edges: DataFrame, sources: DataFrame) -> DataFrame:
    """distribution of the distances from the sources (id): by sets of bits, or of the pair table where the graph is too large for them."""
    return reach.distribution(edges, sources) if reach.fits(edges) else distribution(distances(edges, sources))


def summary(dist: DataFrame, nodes: DataFrame) -> DataFrame:
    """mean_distance, harmonic_diameter, reachable (diagonal included) from a distribution."""
    n = nodes.agg(F.count(F.lit(1)).alias("n"))
    far = F.col("d") > 0
    s = dist.agg(F.sum(F.when(far, F.col("d") * F.col("pairs"))).alias("s"), F.sum(F.when(far, F.col("pairs"))).alias("p"), F.sum(F.when(far, F.col("pairs") / F.col("d"))).alias("h"), F.sum("pairs").alias("all"))
    return s.crossJoin(F.broadcast(n)).select(F.round(F.col("s") / F.col("p"), 6).alias("mean_distance"), F.round(F.col("n") * (F.col("n") - 1) / F.col("h"), 6).alias("harmonic_diameter"), F.round(F.col("all") / (F.col("n") * F.col("n")), 6).alias("reachable"))


def reversed_edges(edges: DataFrame) -> DataFrame:
    return edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"))


def harmonic_exact(edges: DataFrame, nodes: DataFrame, sources: DataFrame | None = None) -> DataFrame:
    """id, harmonic: the sum over other nodes of one over their distance to it.

    With sources, only those nodes' distances are summed and the sum is scaled to all.
    """
    own = nodes if sources is None else sources
    if reach.fits(edges):
        sums = reach.harmonic(edges, own)
    else:
        sums = distances(edges, own).filter("d > 0").groupBy(F.col("node").alias("id")).agg(F.sum(1 / F.col("d")).alias("h"))
    scale = None if sources is None else nodes.agg(F.count(F.lit(1)).alias("n")).crossJoin(sources.agg(F.count(F.lit(1)).alias("k"))).select((F.col("n") / F.col("k")).alias("scale"))
    out = nodes.select("id").join(sums, "id", "left").withColumn("harmonic", F.coalesce("h", F.lit(0.0)))
    return (out if scale is None else out.crossJoin(F.broadcast(scale)).withColumn("harmonic", F.col("harmonic") * F.col("scale"))).select("id", "harmonic")


def harmonic_sketch(edges: DataFrame, nodes: DataFrame, lg_k: int = 12, most: int | None = None) -> tuple[DataFrame, DataFrame]:
    """(id, harmonic, distribution d and pairs) from HyperLogLog balls grown by one hop a round.

    Each round sends the balls that the round before has changed along the edges: what receives
    another one has it already. Nodes' memory is a sketch, not a set. It ends when no ball grows,
    or after `most` hops if that is set.
    """
    balls = step_table(nodes.groupBy("id").agg(F.hll_sketch_agg("id", lg_k).alias("ball")).withColumn("size", F.lit(1.0)).withColumn("harmonic", F.lit(0.0)).withColumn("changed", F.lit(True)))
    totals = [(0, balls.agg(F.sum("size").alias("s")).first()["s"] or 0.0)]
    for d in count(1) if most is None else range(1, most + 1):
        sent = edges.join(balls.filter("changed").select(F.col("id").alias("src"), "ball"), "src").select(F.col("dst").alias("id"), "ball").unionByName(balls.select("id", "ball"))
        grown = sent.groupBy("id").agg(F.hll_union_agg("ball").alias("ball")).withColumn("now", F.hll_sketch_estimate("ball").cast("double"))
        more = F.col("harmonic") + F.greatest(F.col("now") - F.col("size"), F.lit(0.0)) / d
        grown = grown.join(balls.select("id", F.col("ball").alias("before"), "size", "harmonic"), "id")
        balls = step_table(grown.select("id", "ball", F.greatest("now", "size").alias("size"), more.alias("harmonic"), (F.col("ball") != F.col("before")).alias("changed")))
        s = balls.agg(F.sum("size").alias("s")).first()["s"] or 0.0
        if s == totals[-1][1]:
            break
        totals.append((d, s))
    at = nodes.sparkSession.createDataFrame([(d, s - (totals[k - 1][1] if k else 0)) for k, (d, s) in enumerate(totals)], "d int, pairs double")
    return balls.select("id", "harmonic"), at


def pagerank(edges: DataFrame, nodes: DataFrame, alpha: float = 0.85, iterations: int = 20, tol: float = 0.0, dangling: str = "preference", preference: DataFrame | None = None, weighted: bool = False) -> DataFrame:
    """id, rank, by power iteration from the preference vector (uniform unless given as id, v).

    dangling: where the rank of nodes without out-edges goes: preference, self, or drop. tol ends
    the iteration when the sum of changes is at most that; it is then read once in four rounds.
    """
    if dangling not in ("preference", "self", "drop"):
        raise ValueError(f"dangling is preference, self or drop, not {dangling!r}")
    n = nodes.count()
    weight = F.col("links").cast("double") if weighted else F.lit(1.0)
    out = edges.groupBy("src").agg(F.sum(weight).alias("total"))
    arcs = step_table(edges.join(out, "src").select("src", "dst", (weight / F.col("total")).alias("p")))
    v = preference.select("id", "v") if preference is not None else nodes.select("id", F.lit(1.0 / max(1, n)).alias("v"))
    base = step_table(nodes.select("id").join(v, "id", "left").join(out.select(F.col("src").alias("id"), F.lit(True).alias("has")), "id", "left").select("id", F.coalesce("v", F.lit(0.0)).alias("v"), F.col("has").isNull().alias("dangles")))
    ranks = base.select("id", F.col("v").alias("rank"))
    for k in range(iterations):
        inflow = arcs.join(ranks.withColumnRenamed("id", "src"), "src").groupBy(F.col("dst").alias("id")).agg(F.sum(F.col("rank") * F.col("p")).alias("r"))
        rows = base.join(ranks, "id").join(inflow, "id", "left").withColumn("r", F.coalesce("r", F.lit(0.0)))
        if dangling == "preference":
            lost = base.filter("dangles").join(ranks, "id").agg(F.coalesce(F.sum("rank"), F.lit(0.0)).alias("lost"))
            rows = rows.crossJoin(F.broadcast(lost)).withColumn("r", F.col("r") + F.col("lost") * F.col("v"))
        elif dangling == "self":
            rows = rows.withColumn("r", F.col("r") + F.when(F.col("dangles"), F.col("rank")).otherwise(0.0))
        rows = rows.select("id", (alpha * F.col("r") + (1 - alpha) * F.col("v")).alias("rank"), F.col("rank").alias("before"))
        stop = False
        if tol and k % 4 == 3:
            rows = step_table(rows)
            stop = (rows.agg(F.sum(F.abs(F.col("rank") - F.col("before"))).alias("e")).first()["e"] or 0.0) <= tol
        elif k % 4 == 3:
            rows = step_table(rows)
        ranks = rows.select("id", "rank")
        if stop:
            break
    return ranks


def residual(edges: DataFrame, nodes: DataFrame, ranks: DataFrame, alpha: float = 0.85) -> DataFrame:
    """residual: by how much the ranks miss their equation, in sum."""
    n = nodes.agg(F.count(F.lit(1)).alias("n"))
    out = edges.groupBy("src").agg(F.count(F.lit(1)).alias("total"))
    inflow = edges.join(out, "src").join(ranks.withColumnRenamed("id", "src"), "src").groupBy(F.col("dst").alias("id")).agg(F.sum(F.col("rank") / F.col("total")).alias("r"))
    lost = ranks.join(out.select(F.col("src").alias("id")), "id", "left_anti").agg(F.coalesce(F.sum("rank"), F.lit(0.0)).alias("lost"))
    rows = ranks.join(inflow, "id", "left").crossJoin(F.broadcast(n)).crossJoin(F.broadcast(lost))
    due = alpha * (F.coalesce("r", F.lit(0.0)) + F.col("lost") / F.col("n")) + (1 - alpha) / F.col("n")
    return rows.agg(F.sum(F.abs(F.col("rank") - due)).alias("residual"), F.sum("rank").alias("total"))


def indegree(edges: DataFrame, nodes: DataFrame) -> DataFrame:
    return nodes.select("id").join(edges.groupBy(F.col("dst").alias("id")).agg(F.count(F.lit(1)).alias("indegree")), "id", "left").select("id", F.coalesce("indegree", F.lit(0)).alias("indegree"))


def top(scores: DataFrame, column: str, k: int = 10, digits: int = 9) -> DataFrame:
    """place, node, value: the k highest, ties by id."""
    best = scores.select(F.col("id").alias("node"), F.round(F.col(column).cast("double"), digits).alias("value")).orderBy(F.col("value").desc(), "node").limit(k)
    return best.withColumn("place", F.row_number().over(Window.orderBy(F.col("value").desc(), "node")))


def table(edges: DataFrame, nodes: DataFrame, k: int = 10, iterations: int = 20) -> DataFrame:
    """place, and node and value by indegree, PageRank and harmonic centrality."""
    found = {"indegree": indegree(edges, nodes), "rank": pagerank(edges, nodes, iterations=iterations), "harmonic": harmonic_exact(edges, nodes)}
    out = None
    for name, scores in found.items():
        one = top(scores, name, k, 6).select("place", F.col("node").alias(f"{name}_node"), F.col("value").alias(name))
        out = one if out is None else out.join(one, "place")
    return out
