"""Whether a degree histogram follows a power law: fit by likelihood, distance, and bootstrap."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def zeta(a: np.ndarray | float, q: float) -> np.ndarray:
    """The Hurwitz zeta function for a > 1, by direct terms and an Euler-Maclaurin tail."""
    a = np.asarray(a, float)
    n = 20
    head = sum((q + k) ** -a for k in range(n))
    x = q + n
    tail = x ** (1 - a) / (a - 1) + 0.5 * x**-a
    term = a * x ** (-a - 1)
    tail = tail + term / 12 - term * (a + 1) * (a + 2) / x**2 / 720 + term * (a + 1) * (a + 2) * (a + 3) * (a + 4) / x**4 / 30240
    return head + tail


def _alpha(mean_log: float, xmin: float) -> float:
    """The exponent of highest likelihood, by golden section."""
    lo, hi, g = 1.01, 6.0, (np.sqrt(5) - 1) / 2
    cost = lambda a: float(np.log(zeta(a, xmin)) + a * mean_log)
    x, y = hi - g * (hi - lo), lo + g * (hi - lo)
    fx, fy = cost(x), cost(y)
    for _ in range(45):
        if fx < fy:
            hi, y, fy = y, x, fx
            x = hi - g * (hi - lo)
            fx = cost(x)
        else:
            lo, x, fx = x, y, fy
            y = lo + g * (hi - lo)
            fy = cost(y)
    return (lo + hi) / 2


def fit_histogram(degree: np.ndarray, freq: np.ndarray, least_tail: int = 50) -> tuple[float, int, float, int]:
    """(alpha, xmin, KS distance, tail size) of the xmin with the least distance; degrees sorted, positive."""
    best = (0.0, 0, 1.0, 0)
    below = np.concatenate([[0], np.cumsum(freq)])
    for k in range(len(degree)):
        x, f = degree[k:], freq[k:]
        n = int(below[-1] - below[k])
        if n < least_tail or len(x) < 2:
            break
        a = _alpha(float((f * np.log(x)).sum() / n), float(x[0]))
        whole = zeta(a, float(x[0]))
        model = 1 - np.array([float(zeta(a, float(v) + 1)) for v in x]) / whole
        ks = float(np.abs(np.cumsum(f) / n - model).max())
        if ks < best[2]:
            best = (a, int(x[0]), ks, n)
    return best


def fit(freq: DataFrame) -> DataFrame:
    """alpha, xmin, ks, tail of a histogram (degree, freq), which has a row for each degree that occurs."""

    def one(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("degree")
        return pd.DataFrame([fit_histogram(pdf["degree"].to_numpy(), pdf["freq"].to_numpy())], columns=["alpha", "xmin", "ks", "tail"])

    return freq.filter("degree > 0").groupBy(F.lit(1).alias("g")).applyInPandas(one, "alpha double, xmin long, ks double, tail long")


def _draw(rng: np.random.Generator, alpha: float, xmin: int, n: int, most: int) -> np.ndarray:
    """n draws of the law, by its tail sums up to `most` and by the continuous form beyond."""
    grid = np.arange(xmin, most + 1)
    tail = np.array([float(zeta(alpha, float(v))) for v in grid]) / float(zeta(alpha, float(xmin)))
    u = rng.random(n)
    k = np.searchsorted(-tail, -u, side="right") - 1
    out = grid[np.maximum(k, 0)].astype(np.int64)
    far = u < tail[-1]
    out[far] = np.minimum(1 << 40, (most * (u[far] / tail[-1]) ** (-1 / (alpha - 1)))).astype(np.int64)
    return out


def pvalue(freq: DataFrame, replicas: int = 200, seed: int = 7) -> DataFrame:
    """replicas, at_least (whose KS reaches the observed), p. Replicas are seeded by number and spread over tasks."""
    rows = sorted((r["degree"], r["freq"]) for r in freq.filter("degree > 0").collect())
    x, f = np.array([r[0] for r in rows]), np.array([r[1] for r in rows])
    alpha, xmin, ks, tail = fit_histogram(x, f)
    n, body = int(f.sum()), x < xmin
    spark = freq.sparkSession
    held = spark.sparkContext.broadcast((x[body], f[body]))

    def draw(batches):
        bx, bf = held.value
        for pdf in batches:
            out = []
            for i in pdf["id"]:
                rng = np.random.default_rng([seed, int(i)])
                m = rng.binomial(n, tail / n) if len(bx) else n
                parts = [_draw(rng, alpha, xmin, m, max(int(x[-1]), xmin + 1))]
                if n - m:
                    parts.append(rng.choice(bx, n - m, p=bf / bf.sum()))
                d, c = np.unique(np.concatenate(parts), return_counts=True)
                out.append(fit_histogram(d, c)[2])
            yield pd.DataFrame({"ks": out})

    found = spark.range(0, replicas, 1, min(replicas, 64)).mapInPandas(draw, "ks double")
    return found.agg(F.count(F.lit(1)).alias("replicas"), F.count_if(F.col("ks") >= ks).alias("at_least")).withColumn("p", F.col("at_least") / F.col("replicas"))


def approximate_alpha(freq: DataFrame, xmin: int) -> DataFrame:
    """The closed approximation of the exponent over a tail."""
    tail = freq.filter(F.col("degree") >= xmin)
    return tail.agg(F.sum("freq").alias("tail"), F.round(1 + F.sum("freq") / F.sum(F.col("freq") * F.log(F.col("degree") / (xmin - 0.5))), 6).alias("alpha"))
