"""Functions for SQL users: register(spark) adds grid_encode, heavy_light, split_line, explode_blocks and nearest_cell."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf
from pyspark.sql.types import DoubleType, IntegerType, Row

from ..operators.line import line_kmeans


@pandas_udf(IntegerType())
def grid_encode(value: pd.Series, upper: pd.Series) -> pd.Series:
    """The segment of a number by an array of upper ends."""
    return pd.Series([None if v is None or np.isnan(v) else int(min(np.searchsorted(u, v, "left"), len(u) - 1)) for v, u in zip(value.astype(float), upper, strict=True)], dtype="Int32")


@pandas_udf(IntegerType())
def nearest_cell(point: pd.Series, centers: pd.Series) -> pd.Series:
    """The id of the nearest of an array of centers."""
    return pd.Series([int(((np.stack(c) - np.asarray(p)) ** 2).sum(1).argmin()) for p, c in zip(point, centers, strict=True)], dtype="int32")


@pandas_udf(DoubleType())
def weighted_median(value: pd.Series, weight: pd.Series) -> float:
    """The smaller weighted median of a group."""
    keep = weight > 0
    if not keep.any():
        return float("nan")
    order = np.argsort(value[keep].to_numpy(), kind="stable")
    x, w = value[keep].to_numpy()[order], weight[keep].to_numpy()[order]
    return float(x[np.searchsorted(np.cumsum(w), w.sum() / 2, "left")])


@udtf(returnType="comp int, center double, hi double, cost double")
class SplitLine:
    """split_line(values, weights, kappa): the segments of an optimal clustering of weighted numbers."""

    def eval(self, values: list, weights: list, kappa: int) -> Iterator[tuple]:
        line = line_kmeans(values, weights, kappa)
        for i, (c, h) in enumerate(zip(line.centers, line.upper, strict=True)):
            yield i, float(c), float(h), float(line.cost)


@udtf(returnType="comp int, category string, weight double, kind string")
class HeavyLight:
    """heavy_light(categories, weights, kappa): the heaviest categories, and the rest as one row."""

    def eval(self, categories: list, weights: list, kappa: int) -> Iterator[tuple]:
        rows = sorted(zip(categories, weights, strict=True), key=lambda r: (-r[1], r[0]))
        for i, (c, w) in enumerate(rows[: kappa - 1]):
            yield i, c, float(w), "heavy"
        if len(rows) > kappa - 1:
            yield kappa - 1, None, float(sum(w for _, w in rows[kappa - 1 :])), "light"


@udtf(returnType="block int, part array<double>")
class ExplodeBlocks:
    """explode_blocks(vector, size): a vector's blocks."""

    def eval(self, vector: list, size: int) -> Iterator[Row]:
        for i in range(0, len(vector), size):
            yield i // size, [float(v) for v in vector[i : i + size]]


def register(spark: SparkSession) -> None:
    spark.udf.register("grid_encode", grid_encode)
    spark.udf.register("nearest_cell", nearest_cell)
    spark.udf.register("weighted_median", weighted_median)
    spark.udtf.register("split_line", SplitLine)
    spark.udtf.register("heavy_light", HeavyLight)
    spark.udtf.register("explode_blocks", ExplodeBlocks)
