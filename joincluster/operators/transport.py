"""Optimal transport between discrete measures: the reading of the method as measure projections."""

from __future__ import annotations

from functools import reduce

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from .lloyd import nearest


def wasserstein_1d(p: DataFrame, q: DataFrame, power: int = 1) -> DataFrame:
    """One row, wp: the distance of two measures on numbers (x, w), each normalised, by coupling equal quantiles.

    The breakpoints of both cumulative masses are merged; between two of them each measure sits at one
    value. Running sums need one order, so the measures must be marginals of bounded support, as
    buckets or rounded values are.
    """

    def steps(df, name):
        w = W.orderBy("x")
        total = df.agg(F.sum(F.col("w").cast("double")).alias("t"))
        return df.groupBy("x").agg(F.sum(F.col("w").cast("double")).alias("w")).crossJoin(F.broadcast(total)).select(F.round(F.sum("w").over(w.rowsBetween(W.unboundedPreceding, 0)) / F.col("t"), 12).alias("c"), F.col("x").cast("double").alias(name))

    a, b = steps(p, "xa"), steps(q, "xb")
    both = a.withColumn("xb", F.lit(None).cast("double")).unionByName(b.withColumn("xa", F.lit(None).cast("double"))).groupBy("c").agg(F.min("xa").alias("xa"), F.min("xb").alias("xb"))
    back = W.orderBy("c").rowsBetween(0, W.unboundedFollowing)
    filled = both.select("c", F.first("xa", ignorenulls=True).over(back).alias("xa"), F.first("xb", ignorenulls=True).over(back).alias("xb"), (F.col("c") - F.coalesce(F.lag("c").over(W.orderBy("c")), F.lit(0.0))).alias("d"))
    return filled.agg(F.pow(F.sum(F.col("d") * F.pow(F.abs(F.col("xa") - F.col("xb")), power)), 1.0 / power).alias("wp"))


def coupling_small(p: list[float], q: list[float], cost) -> tuple[np.ndarray, float]:
    """A cheapest coupling of two small measures and its cost, by successive shortest paths. For tests: a few hundred points."""
    a, b, c = np.array(p, float) / sum(p), np.array(q, float) / sum(q), np.asarray(cost, float)
    n, m = len(a), len(b)
    flow, u, v = np.zeros((n, m)), np.zeros(n), np.zeros(m)
    while a.max() > 1e-12:
        dist, dist_b = np.where(a > 1e-12, 0.0, np.inf), np.full(m, np.inf)
        prev_a, prev_b = np.full(n, -1), np.full(m, -1)
        while True:
            step = c - u[:, None] - v[None, :]
            to_b = dist[:, None] + step
            nb, at = to_b.min(0), to_b.argmin(0)
            better = nb < dist_b - 1e-15
            dist_b[better], prev_b[better] = nb[better], at[better]
            to_a = np.where(flow > 1e-15, dist_b[None, :] - step, np.inf)
            na, at_a = to_a.min(1), to_a.argmin(1)
            back = na < dist - 1e-15
            dist[back], prev_a[back] = na[back], at_a[back]
            if not better.any() and not back.any():
                break
        j = int(np.where(b > 1e-12, dist_b, np.inf).argmin())
        path, x = [], j
        while True:
            i = int(prev_b[x])
            path.append((i, x, 1))
            if prev_a[i] < 0:
                break
            path.append((i, int(prev_a[i]), -1))
            x = int(prev_a[i])
        amount = min(a[i], b[j], *[flow[s, t] for s, t, sign in path if sign < 0])
        for s, t, sign in path:
            flow[s, t] += sign * amount
        a[i] -= amount
        b[j] -= amount
        reach = min(dist_b[j], 1e300)
        u -= np.minimum(np.where(np.isfinite(dist), dist, reach), reach) - reach
        v += np.minimum(np.where(np.isfinite(dist_b), dist_b, reach), reach) - reach
    return flow, float((flow * c).sum())


def wasserstein_small(x, p, y, q, power: int = 2) -> float:
    """The distance of order power of two small measures on vectors, exactly."""
    x, y = np.atleast_2d(np.asarray(x, float).T).T, np.atleast_2d(np.asarray(y, float).T).T
    cost = (np.abs(x[:, None, :] - y[None, :, :]) ** power).sum(2)
    return max(coupling_small(list(p), list(q), cost)[1], 0.0) ** (1 / power)


def transport_to_support(grid: DataFrame, centroids, p: int = 2) -> float:
    """Cost of moving the cells to a fixed support with free masses: everything goes to its nearest point."""
    return float(nearest(grid, centroids, p).agg(F.sum(F.col("w") * F.col("d"))).first()[0] or 0.0)


def measures(result) -> dict[str, DataFrame]:
    """The method's measures: the subspaces' projections, the grid's, and the final one; masses sum to 1."""
    spark = result.cells.sparkSession
    parts = [spark.createDataFrame([(s.name, i, float(m)) for i, m in enumerate(s.mass)], "subspace string, point int, mass double") for s in result.comps.subspaces]
    projections = reduce(DataFrame.unionByName, parts)
    total = projections.groupBy("subspace").agg(F.sum("mass").alias("t"))
    cells = result.cells.withColumn("mass", F.col("w") / F.lit(float(result.cells.agg(F.sum("w")).first()[0] or 1)))
    return {
        "subspaces": projections.join(F.broadcast(total), "subspace").select("subspace", "point", (F.col("mass") / F.col("t")).alias("mass")),
        "grid": cells.drop("w"),
        "final": nearest(result.cells, result.centroids).groupBy(F.col("cluster").alias("point")).agg(F.sum("w").alias("w")).select("point", (F.col("w") / F.lit(float(result.cells.agg(F.sum("w")).first()[0] or 1))).alias("mass")),
    }
