"""Cost and accuracy measures."""

from __future__ import annotations

import resource
import time
from contextlib import contextmanager
from dataclasses import replace
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.hypergraph import decompose
from ..plans.messages import Calibration
from ..plans.spec import FeatureQuery
from .components import ComponentSet
from .lloyd import Centroids, nearest


def _parts(query: FeatureQuery, centroids: Centroids, marginals: DataFrame) -> tuple[dict[str, DataFrame], list[list[float]]]:
    """For each categorical feature: category, coordinates in every cluster; and each feature's squared norms by cluster."""
    import numpy as np

    tables, norms = {}, []
    for s, a in zip(centroids.comps.subspaces, centroids.coef, strict=True):
        if s.heavy is None:
            norms.append([])
            continue
        q = np.ones(a.shape[1])
        if s.has_light:
            q[len(s.heavy)] = s.sqnorm
        norms.append([float(v) for v in (a * a * q).sum(1)])
        cats = marginals.where(F.col("subspace") == s.name).select(F.col("vcat").alias(s.name), F.col("w").cast("double").alias("v"))
        at = s.encode(F.col(s.name))
        rows = F.element_at(F.array(*[F.array(*[F.lit(float(x)) for x in a[:, c]]) for c in range(a.shape[1])]), at + 1)
        share = F.when(at >= len(s.heavy), F.col("v") / F.lit(float(s.mass[-1]))).otherwise(F.lit(1.0)) if s.has_light else F.lit(1.0)
        tables[s.name] = cats.select(s.name, F.transform(rows, _times(share)).alias(f"m_{s.name}"))
    return tables, norms


def _times(share):
    return lambda v: v * share


def row_distances(x: DataFrame, query: FeatureQuery, centroids: Centroids, marginals: DataFrame) -> DataFrame:
    """x with ds: its squared distance to every centroid, from explicit coordinates."""
    tables, norms = _parts(query, centroids, marginals)
    out, per = x, []
    for j, (s, n) in enumerate(zip(centroids.comps.subspaces, norms, strict=True)):
        lam = s.feature.scale**2
        if s.heavy is None:
            centers = [float(v) for v in centroids.value(j)]
            per.append(F.array(*[(F.col(s.name) - F.lit(v)) * (F.col(s.name) - F.lit(v)) * lam for v in centers]))
        else:
            out = out.join(tables[s.name], s.name, "left")
            none = F.array(*[F.lit(0.0)] * centroids.k)
            per.append(F.zip_with(F.coalesce(f"m_{s.name}", none), F.array(*[F.lit(v) for v in n]), _onehot(lam)))
    total = reduce(lambda a, b: F.zip_with(a, b, lambda p, q: p + q), per)
    return out.withColumn("ds", total).drop(*[f"m_{n}" for n in tables])


def _onehot(lam: float):
    return lambda m, n: F.greatest(1.0 - 2.0 * m + n, F.lit(0.0)) * lam


def objective(x: DataFrame, query: FeatureQuery, centroids: Centroids, marginals: DataFrame) -> float:
    """Sum over the matrix's rows of the squared distance to the nearest centroid."""
    return float(row_distances(x, query, centroids, marginals).agg(F.sum(F.col("w") * F.array_min("ds"))).first()[0] or 0.0)


def grid_objective(cells: DataFrame, centroids: Centroids, p: int = 2) -> float:
    return float(nearest(cells, centroids, p).agg(F.sum(F.col("w") * F.col("d"))).first()[0] or 0.0)


def quantisation_cost(comps: ComponentSet) -> float:
    return comps.cost


def relative_approx(ours: float, base: float) -> float:
    """(ours - base) / base, as the reported values imply."""
    return ours / base - 1


def relative_speedup(materialise: float, cluster: float, ours: float, limit: float | None = None) -> float:
    """Baseline seconds over ours; a baseline that ran out of time counts its limit alone."""
    return (limit if limit is not None else materialise + cluster) / ours


def compression(rows: int, cells: int) -> float:
    return rows / cells if cells else 0.0


def induced_cost(query: FeatureQuery, comps: ComponentSet, centroids: Centroids, marginals: DataFrame) -> float:
    """Cost of the matrix when each row goes to the cluster of its cell, without the matrix: one grid with one raw feature at a time."""
    total = 0.0
    for j, s in enumerate(comps.subspaces):
        raw = Calibration(_rooted(query, s.name)).grid(comps.encoders, comps.defaults, keep={f"r_{s.name}": F.col(f"f__{s.name}")})
        got = nearest(raw.withColumnRenamed(f"r_{s.name}", "raw"), centroids).groupBy("cluster", "raw").agg(F.sum("w").alias("w"))
        if s.heavy is None:
            mu = F.element_at(F.array(*[F.lit(float(v)) for v in centroids.value(j)]), F.col("cluster") + 1)
            cost = (F.col("raw") - mu) * (F.col("raw") - mu)
        else:
            tables, norms = _parts(query, centroids, marginals)
            got = got.join(tables[s.name].withColumnRenamed(s.name, "raw"), "raw")
            n = F.element_at(F.array(*[F.lit(v) for v in norms[j]]), F.col("cluster") + 1)
            cost = 1.0 - 2.0 * F.element_at(f"m_{s.name}", F.col("cluster") + 1) + n
        total += s.feature.scale**2 * float(got.agg(F.sum(F.col("w") * cost)).first()[0] or 0.0)
    return total


def _rooted(query: FeatureQuery, feature: str) -> FeatureQuery:
    """The query with its tree hung from a feature's relation, so that the feature's raw values pass no join but the root's own. Left joins keep their root."""
    q = decompose(query.validate())
    return q if any(e.how == "left" for e in q.edges) else replace(q, root=q.feature(feature).relation)


def distinct_profile(df: DataFrame, column: str, decimals: tuple[int, ...], approximate: bool = False) -> DataFrame:
    """decimals, n: distinct values of a column after rounding."""
    count = F.approx_count_distinct if approximate else F.count_distinct
    return reduce(DataFrame.unionByName, [df.agg(count(F.round(F.col(column), d)).cast("bigint").alias("n")).select(F.lit(d).alias("decimals"), "n") for d in decimals])


def zscores(marginals: DataFrame) -> DataFrame:
    """subspace, n, mean, sd of the numeric features, from their marginals alone."""
    w, x = F.col("w").cast("double"), F.col("vnum")
    s = marginals.where("vnum is not null").groupBy("subspace").agg(F.sum("w").cast("bigint").alias("n"), F.sum(w * x).alias("s"), F.sum(w * x * x).alias("q"))
    return s.select("subspace", "n", (F.col("s") / F.col("n")).alias("mean"), F.sqrt(F.greatest(F.col("q") / F.col("n") - (F.col("s") / F.col("n")) * (F.col("s") / F.col("n")), F.lit(0.0))).alias("sd"))


def matrix_stats(query: FeatureQuery, marginals: DataFrame) -> DataFrame:
    """relations, attributes, onehot_width, input_rows, matrix_rows."""
    width = marginals.agg(F.count("vcat").alias("c"), F.count_distinct(F.when(F.col("vnum").isNotNull(), F.col("subspace"))).alias("n")).first()
    cal = Calibration(query)
    rows = cal.size
    cal.release()
    inputs = sum(df.count() for df in query.relations.values())
    return marginals.sparkSession.createDataFrame([(query.name, len(query.relations), len(query.features), int(width["c"] + width["n"]), inputs, rows)], "workload string, relations int, attributes int, onehot_width bigint, input_rows bigint, matrix_rows bigint")


def peak_memory() -> int:
    """Bytes that this process and its ended children held at most."""
    return 1024 * max(resource.getrusage(w).ru_maxrss for w in (resource.RUSAGE_SELF, resource.RUSAGE_CHILDREN))


class StepTimer:
    """Seconds of named steps."""

    def __init__(self):
        self.seconds: dict[str, float] = {}

    @contextmanager
    def __call__(self, name: str):
        t = time.perf_counter()
        try:
            yield
        finally:
            self.seconds[name] = self.seconds.get(name, 0.0) + time.perf_counter() - t
