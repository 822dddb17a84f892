"""Subspaces of several numbers: blocks of an array column, clustered by any weighted solver."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .baseline import dense_lloyd


def blocks(column: str, width: int, size: int) -> list[Column]:
    """An array column of width numbers, cut into blocks of the given size."""
    return [F.transform(F.slice(column, i + 1, size), lambda x: x.cast("double")).alias(f"b{i // size}") for i in range(0, width, size)]


def vector_kmeans(df: DataFrame, column: str, kappa: int, solver: str = "mllib", seed: int = 1, weight: str | None = None) -> np.ndarray:
    """kappa centers of an array column. solver: mllib (distributed), or dense (exact Lloyd on the distinct vectors, few of them, from the heaviest)."""
    w = F.col(weight).cast("double") if weight else F.lit(1.0)
    if solver == "dense":
        rows = df.groupBy(column).agg(F.sum(w).alias("w")).orderBy(F.desc("w"), column).toPandas()
        x = np.array(rows[column].tolist(), float)
        return dense_lloyd(x, rows["w"].to_numpy(), x[: min(kappa, len(x))])[0]
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector

    v = df.select(array_to_vector(column).alias("features"), w.alias("w"))
    return np.array(KMeans(k=kappa, seed=seed, weightCol="w").fit(v).clusterCenters())


def nearest_center(column: str, centers: np.ndarray) -> Column:
    """The id of the nearest center of an array column, ties to the smallest."""
    d = F.array(*[F.aggregate(F.zip_with(column, F.array(*[F.lit(float(v)) for v in c]), lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda a, v: a + v) for c in centers])
    return F.array_position(d, F.array_min(d)).cast("int") - 1


def block_grid(df: DataFrame, column: str, width: int, size: int, kappa: int, label: str | None = None, solver: str = "mllib") -> tuple[DataFrame, list[np.ndarray]]:
    """The grid of an array column's blocks (and a categorical column): c_b0..., w; and each block's centers."""
    names = [f"b{i}" for i in range(-(-width // size))]
    x = df.select(*blocks(column, width, size), *([F.col(label).alias("label")] if label else []))
    centers = [vector_kmeans(x, b, kappa, solver) for b in names]
    cells = x.select(*[nearest_center(b, c).alias(f"c_{b}") for b, c in zip(names, centers, strict=True)], *([F.col("label").alias("c_label")] if label else []))
    return cells.groupBy(*cells.columns).agg(F.count("*").alias("w")), centers
