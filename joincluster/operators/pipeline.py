"""The method end to end."""

from __future__ import annotations

from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.messages import Calibration
from ..plans.spec import FeatureQuery
from .bounds import approx_bound
from .components import ComponentSet, solve
from .lloyd import Centroids, Clustering, Penalty, grid_lloyd, nearest, seed_parallel, seed_pp, seed_top
from .objective import StepTimer, zscores


@dataclass
class ClusterResult:
    query: FeatureQuery
    marginals: DataFrame
    comps: ComponentSet
    cells: DataFrame
    clustering: Clustering
    seconds: dict[str, float] = field(default_factory=dict)
    plain: bool = True  # squared distances and no penalty

    @property
    def centroids(self) -> Centroids:
        return self.clustering.centroids

    def assignment(self) -> DataFrame:
        return nearest(self.cells, self.centroids)

    def sizes(self) -> DataFrame:
        """cluster, weight, cells."""
        return self.assignment().groupBy("cluster").agg(F.sum("w").cast("bigint").alias("weight"), F.count("*").alias("cells"))

    def guarantee(self, gamma: float) -> float | None:
        """The ratio that holds if the last step is gamma-optimal; None where a subspace's solver has no proven ratio (buckets,
        Lloyd, weighted categories) and for p = 1 and penalties."""
        known = self.plain and all(s.exact and not s.feature.category_scale for s in self.comps.subspaces)
        return approx_bound(1.0, gamma) if known else None


def scaled(query: FeatureQuery, marginals: DataFrame) -> FeatureQuery:
    """The query with numeric features divided by their deviation over the joined rows, from the marginals alone."""
    sd = {r["subspace"]: r["sd"] for r in zscores(marginals).collect()}
    return replace(query, features=[replace(f, scale=f.scale / sd[f.name]) if sd.get(f.name) else f for f in query.features])


def cluster_join(
    spark: SparkSession, query: FeatureQuery, k: int, kappa: int | dict[str, int] | None = None, *, seeding: str = "pp", seed: int = 1, max_iter: int = 20, tol: float = 1e-4,
    p: int = 2, penalty: Penalty | None = None, scaling: str = "none", weight: str = "bigint", local: bool | None = None, method: str = "auto",
) -> ClusterResult:
    """Clusters the rows of a feature query without building its matrix.

    kappa None means k components a subspace (the regime of the guarantee); a number or a dict by
    feature sets them. p = 1 gives medians, penalty a regularised clustering, scaling='zscore' unit
    deviations. Steps are timed: marginals, subspaces, grid, clustering.
    """
    timer, kappa = StepTimer(), k if kappa is None else kappa
    with timer("marginals"):
        cal = Calibration(query, weight)
        marginals = cal.marginals().persist()
        marginals.count()
        if scaling == "zscore":
            query = scaled(query, marginals)
    with timer("subspaces"):
        comps = solve(query, marginals, kappa, method, p, penalty.lam if penalty and penalty.kind == "l1" else 0.0)
    with timer("grid"):
        cells = cal.grid(comps.encoders, comps.defaults).persist()
        cells.count()
    with timer("clustering"):
        seeds = {"pp": lambda: seed_pp(cells, comps, k, seed), "parallel": lambda: seed_parallel(cells, comps, k, seed), "top": lambda: seed_top(cells, comps, k)}[seeding]()
        clustering = grid_lloyd(cells, comps, seeds, max_iter, tol, p, penalty, local)
    cal.release()
    return ClusterResult(query, marginals, comps, cells, clustering, timer.seconds, p == 2 and penalty is None)
