"""Optimal clustering of one categorical feature: the heaviest categories alone, all others together."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W


@dataclass
class HeavyLight:
    """heavy: (category, weight), heaviest first; the rest has weight light, squared norm sqnorm and its heaviest category top."""

    heavy: list[tuple[str, float]]
    light: float
    sqnorm: float
    cost: float
    top: float = 0.0

    @property
    def median_cost(self) -> float:
        """The cost for p = 1: the light part's weight, or twice what its heaviest category leaves."""
        return min(self.light, 2 * (self.light - self.top))


def ranked(marginal: DataFrame) -> DataFrame:
    """Adds rank, from 1, by falling weight and then by category, within each subspace."""
    return marginal.withColumn("rank", F.row_number().over(W.partitionBy("subspace").orderBy(F.desc("w"), "vcat")))


def heavy_light_table(marginal: DataFrame, kappa: int) -> DataFrame:
    """subspace, comp, kind, vcat, w: kappa - 1 heavy components a subspace and one light one, where there is anything left for it.

    The heavy ones come from a limited rank (a top-k per group); the light one from sums, so no
    subspace's categories are gathered anywhere.
    """
    top = ranked(marginal).where(F.col("rank") < kappa)
    heavy = top.select("subspace", (F.col("rank") - 1).alias("comp"), F.lit("heavy").alias("kind"), "vcat", "w")
    total = marginal.groupBy("subspace").agg(F.sum("w").alias("all"), F.count("*").alias("n"))
    light = total.join(top.groupBy("subspace").agg(F.sum("w").alias("top"), F.count("*").alias("k")), "subspace", "left")
    light = light.where(F.col("n") > F.coalesce("k", F.lit(0)))
    return heavy.unionByName(light.select("subspace", F.coalesce("k", F.lit(0)).cast("int").alias("comp"), F.lit("light").alias("kind"), F.lit(None).cast("string").alias("vcat"), (F.col("all") - F.coalesce("top", F.lit(0))).cast("bigint").alias("w")))


def heavy_light(marginal: DataFrame, kappa: int) -> HeavyLight:
    """The same for one subspace, to the driver: at most kappa numbers, however many categories there are."""
    top = [(r["vcat"], float(r["w"])) for r in marginal.orderBy(F.desc("w"), "vcat").limit(kappa).collect()]
    w = F.col("w").cast("double")
    s = marginal.agg(F.sum(w).alias("w"), F.sum(w * w).alias("q")).first()
    return _heavy_light(top, kappa, float(s["w"] or 0), float(s["q"] or 0))


def heavy_light_local(marginal: list[tuple[str, float]], kappa: int) -> HeavyLight:
    """The same of a marginal (category, weight) that the driver holds."""
    top = sorted(marginal, key=lambda x: (-x[1], x[0]))[:kappa]
    return _heavy_light(top, kappa, sum(w for _, w in marginal), sum(w * w for _, w in marginal))


def _heavy_light(top: list[tuple[str, float]], kappa: int, total: float, squares: float) -> HeavyLight:
    heavy, rest = top[: kappa - 1], top[kappa - 1 :]
    light, squares = total - sum(v for _, v in heavy), squares - sum(v * v for _, v in heavy)
    if light <= 0 or not rest:
        return HeavyLight(heavy, 0.0, 0.0, 0.0)
    return HeavyLight(heavy, light, max(squares, 0.0) / light**2, max(light - squares / light, 0.0), rest[0][1])


def categorical_cost(weights: dict[str, float], parts: list[set[str]], p: int = 2) -> float:
    """The cost of a partition of categories, in closed form; for p = 1 each part costs min(W, 2 (W - max))."""
    out = 0.0
    for part in parts:
        v = [weights[e] for e in part]
        if sum(v) > 0:
            out += sum(v) - sum(x * x for x in v) / sum(v) if p == 2 else min(sum(v), 2 * (sum(v) - max(v)))
    return out


def category_centroid(marginal: DataFrame) -> DataFrame:
    """Adds share: the centroid of each subspace's categories together."""
    return marginal.withColumn("share", F.col("w") / F.sum("w").over(W.partitionBy("subspace")))


def scaled_cost(weights: dict[str, float], scale: dict[str, float], parts: list[set[str]]) -> float:
    """The cost of a partition where category e stands at scale[e] times its unit vector."""
    out = 0.0
    for part in parts:
        total = sum(weights[e] for e in part)
        if total > 0:
            out += sum(weights[e] * scale.get(e, 1.0) ** 2 for e in part) - sum((weights[e] * scale.get(e, 1.0)) ** 2 for e in part) / total
    return out


def scaled_parts(weights: dict[str, float], scale: dict[str, float], kappa: int) -> list[set[str]]:
    """A partition for scaled categories: heavy/light by w s^2, then moves of single categories while they help. Not proven optimal."""
    order = sorted(weights, key=lambda e: (-weights[e] * scale.get(e, 1.0) ** 2, e))
    parts = [{e} for e in order[: kappa - 1]] + ([set(order[kappa - 1 :])] if len(order) >= kappa else [])
    best, moved = scaled_cost(weights, scale, parts), True
    while moved:
        moved = False
        for e in order:
            at = next(i for i, q in enumerate(parts) if e in q)
            for i in range(len(parts)):
                if i != at:
                    trial = [q - {e} if j == at else q | {e} if j == i else q for j, q in enumerate(parts)]
                    if (c := scaled_cost(weights, scale, trial)) < best - 1e-12:
                        parts, best, moved, at = trial, c, True, i
    return [q for q in parts if q]


def in_heavy(column: Column, heavy: list[str]) -> Column:
    return column.isin(heavy) if heavy else F.lit(False)
