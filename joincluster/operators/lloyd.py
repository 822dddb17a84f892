"""Weighted Lloyd on grid cells, with centroids kept as mixtures of each subspace's components.

After an update a centroid is, in every subspace, a convex mixture of its components. Distances to
a mixture need only the mixing coefficients and the light component's squared norm, so an iteration
moves k * m * kappa numbers, whatever the number of categories.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .components import ComponentSet, Subspace

#: Cells times subspaces up to which the driver iterates alone.
LOCAL_MOST = 10_000_000


@dataclass(frozen=True)
class Penalty:
    """l1: lam * |coordinate| on numbers; group: lam * norm of each subspace's part (numbers and categories)."""

    kind: str
    lam: float


@dataclass
class Centroids:
    """coef[j][l, c]: the share of component c in cluster l's part of subspace j."""

    comps: ComponentSet
    coef: list[np.ndarray]

    @property
    def k(self) -> int:
        return len(self.coef[0])

    def distances(self, p: int = 2) -> list[np.ndarray]:
        return [distance_table(s, a, p) for s, a in zip(self.comps.subspaces, self.coef, strict=True)]

    def value(self, j: int) -> np.ndarray:
        """The numeric part of every cluster in subspace j."""
        return self.coef[j] @ self.comps.subspaces[j].centers

    def table(self, spark) -> DataFrame:
        """cluster, subspace, comp, coef."""
        rows = [(l, s.name, c, float(a[l, c])) for s, a in zip(self.comps.subspaces, self.coef, strict=True) for l in range(len(a)) for c in range(a.shape[1]) if a[l, c]]
        return spark.createDataFrame(rows, "cluster int, subspace string, comp int, coef double")

    def expanded(self, marginals: DataFrame) -> DataFrame:
        """cluster, subspace, category, value: the one-hot coordinates; a light category has its share of the light part."""
        spark = marginals.sparkSession
        coef = self.table(spark)
        light = spark.createDataFrame([(s.name, len(s.heavy), float(s.mass[-1])) for s in self.comps.subspaces if s.has_light] or [("", -1, 1.0)], "subspace string, comp int, total double")
        heavy = spark.createDataFrame([(s.name, i, h) for s in self.comps.subspaces if s.heavy for i, h in enumerate(s.heavy)] or [("", -1, "")], "subspace string, comp int, category string")
        numeric = spark.createDataFrame([(l, s.name, None, float(v)) for j, s in enumerate(self.comps.subspaces) if s.heavy is None for l, v in enumerate(self.value(j))] or [(-1, "", None, 0.0)], "cluster int, subspace string, category string, value double").where("cluster >= 0")
        cats = marginals.where("vcat is not null").select("subspace", F.col("vcat").alias("category"), F.col("w").cast("double").alias("w"))
        own = coef.join(F.broadcast(heavy), ["subspace", "comp"]).select("cluster", "subspace", "category", F.col("coef").alias("value"))
        rest = cats.join(F.broadcast(heavy.select("subspace", "category")), ["subspace", "category"], "left_anti").join(F.broadcast(coef.join(light, ["subspace", "comp"])), "subspace")
        return own.unionByName(rest.select("cluster", "subspace", "category", (F.col("coef") * F.col("w") / F.col("total")).alias("value"))).unionByName(numeric)


def distance_table(s: Subspace, a: np.ndarray, p: int = 2) -> np.ndarray:
    """[c, l]: distance (to the power p) of component c to cluster l's part, times the subspace's weight to the power p."""
    if s.heavy is None:
        d = np.abs(s.centers[:, None] - (a @ s.centers)[None, :]) ** p
        return d * s.feature.scale**p
    h = len(s.heavy)
    if p == 1:
        # Coordinates are medians: a cluster's part is one component or nothing. Cells of one component, light ones too, are one point.
        held = a > 0
        d = np.where(held.any(1)[None, :], 2.0 * ~held.T, 1.0)
        return d * s.feature.scale
    norms = np.ones(a.shape[1])
    if s.has_light:
        norms[h] = s.sqnorm
    own = (a * a * norms).sum(1)
    return np.maximum(norms[:, None] * (1 - 2 * a.T) + own[None, :], 0) * s.feature.scale**2


def point_mixtures(comps: ComponentSet, cells: np.ndarray) -> Centroids:
    """Centroids that are grid cells."""
    return Centroids(comps, [np.eye(s.size)[cells[:, j]] for j, s in enumerate(comps.subspaces)])


# ---- seeding --------------------------------------------------------------------------------------


def _cells(grid: DataFrame, comps: ComponentSet) -> list[str]:
    return [f"c_{s.name}" for s in comps.subspaces]


def seed_top(grid: DataFrame, comps: ComponentSet, k: int) -> np.ndarray:
    """The k heaviest cells, ties by their ids."""
    cols = _cells(grid, comps)
    return np.array([list(r) for r in grid.orderBy(F.desc("w"), *cols).limit(k).select(*cols).collect()], dtype=int).reshape(-1, len(cols))


def uniform(seed: int, r: int, cols: list[str]):
    """A number in (0, 1] that the seed, the round and the cell decide, the same on any partitioning and in SQL."""
    text = F.concat_ws(":", F.lit(str(seed)), F.lit(str(r)), *[F.col(c).cast("string") for c in cols])
    return (F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("double") + 1) / F.lit(4294967296.0)


#: Cells times seeds up to which the driver draws the seeds alone.
SEED_LOCAL_MOST = 2_000_000


def seed_pp(grid: DataFrame, comps: ComponentSet, k: int, seed: int = 1, local: bool | None = None) -> np.ndarray:
    """k cells drawn by weight times squared distance to the chosen ones: one race (the least -ln(u) / (w d)) a round.

    The driver races the cells of a small grid; a larger one carries its least distance to the chosen
    cells as a column from round to round. Both draw the same cells.
    """
    cols = _cells(grid, comps)
    if local is None:
        local = grid.count() * k <= SEED_LOCAL_MOST
    if local:
        return _seed_local(grid, comps, k, seed, cols)
    chosen: list[list[int]] = []
    now = grid.withColumn("d", F.lit(1.0))
    for r in range(k):
        raced = now.where("d > 1e-12").withColumn("race", -F.log(uniform(seed, r, cols)) / (F.col("w") * F.col("d")))
        best = raced.orderBy("race", *cols).limit(1).select(*cols).collect()
        if not best:
            break
        chosen.append(list(best[0]))
        now = _least_distances(grid, comps, np.array(chosen))
    return np.array(chosen, dtype=int).reshape(-1, len(cols))


def _least_distances(grid: DataFrame, comps: ComponentSet, chosen: np.ndarray) -> DataFrame:
    """grid with d, the least squared distance to the chosen cells: one vectorised pass."""
    return nearest(grid, point_mixtures(comps, chosen)).drop("cluster")


def _seed_local(grid: DataFrame, comps: ComponentSet, k: int, seed: int, cols: list[str]) -> np.ndarray:
    from hashlib import md5

    held = grid.select(*cols, "w").toArrow()
    cells, w = np.stack([held.column(c).to_numpy() for c in cols], 1).astype(int), held.column("w").to_numpy().astype(float)
    names = [":".join(map(str, x)) for x in cells.tolist()]
    d, chosen = np.ones(len(cells)), []
    for r in range(k):
        some = np.flatnonzero(d > 1e-12)
        if not len(some):
            break
        u = np.array([int(md5(f"{seed}:{r}:{names[i]}".encode()).hexdigest()[:8], 16) for i in some], float)
        race = -np.log((u + 1) / 4294967296.0) / (w[some] * d[some])
        best = some[np.lexsort((*cells[some].T[::-1], race))[0]]
        chosen.append(best)
        now = sum(t[cells[:, j], 0] for j, t in enumerate(point_mixtures(comps, cells[[best]]).distances()))
        d = now if r == 0 else np.minimum(d, now)
    return cells[chosen] if chosen else np.empty((0, len(cols)), int)


def seed_parallel(grid: DataFrame, comps: ComponentSet, k: int, seed: int = 1, rounds: int = 5, oversample: float = 2.0) -> np.ndarray:
    """Oversampled seeding in a few passes: each draws about oversample * k cells, which are then seeded down to k by weight."""
    cols = _cells(grid, comps)
    chosen = seed_pp(grid, comps, 1, seed)
    total = oversample * k
    for r in range(1, rounds + 1):
        d = nearest(grid, point_mixtures(comps, chosen))
        phi = d.agg(F.sum(F.col("w") * F.col("d"))).first()[0] or 0.0
        if phi <= 0:
            break
        got = d.where(uniform(seed, r, cols) < F.lit(total) * F.col("w") * F.col("d") / F.lit(float(phi))).select(*cols).limit(int(10 * total) + 10).collect()
        if got:
            chosen = np.unique(np.vstack([chosen, np.array([list(x) for x in got])]), axis=0)
    near = nearest(grid, point_mixtures(comps, chosen)).groupBy("cluster").agg(F.sum("w").alias("w")).collect()
    w = np.zeros(len(chosen))
    for r in near:
        w[r["cluster"]] = r["w"]
    rng, tables = np.random.default_rng(seed), point_mixtures(comps, chosen).distances()
    dist = sum(t[chosen[:, j]] for j, t in enumerate(tables))
    out = [int(rng.choice(len(chosen), p=w / w.sum()))]
    while len(out) < min(k, len(chosen)):
        p = w * dist[:, out].min(1)
        if p.sum() <= 0:
            break
        out.append(int(rng.choice(len(chosen), p=p / p.sum())))
    return chosen[out]


# ---- iterations -----------------------------------------------------------------------------------

#: Distances that agree to so many decimals are ties; the order in which parts are added decides what lies below.
TIE_DECIMALS = 9


def _sweep(cells: np.ndarray, w: np.ndarray, tables: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    d = sum(t[cells[:, j]] for j, t in enumerate(tables))
    a = np.round(d, TIE_DECIMALS).argmin(1)
    return a, d[np.arange(len(a)), a]


def _masses(cells: np.ndarray, w: np.ndarray, a: np.ndarray, k: int, sizes: list[int]) -> list[np.ndarray]:
    return [np.bincount(a * n + cells[:, j], weights=w, minlength=k * n).reshape(k, n) for j, n in enumerate(sizes)]


def nearest(grid: DataFrame, centroids: Centroids, p: int = 2) -> DataFrame:
    """grid with cluster and d (distance to the power p): one table look-up a subspace, vectorised."""
    cols, tables = _cells(grid, centroids.comps), centroids.distances(p)
    schema = grid.schema.simpleString()[7:-1]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            cells = np.stack([b.column(c).to_numpy() for c in cols], 1).astype(int)
            a, d = _sweep(cells, None, tables)
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(a.astype(np.int32)), pa.array(d)], [*b.schema.names, "cluster", "d"])

    return grid.mapInArrow(run, f"{schema}, cluster int, d double")


def _pass(grid: DataFrame, centroids: Centroids, p: int) -> tuple[list[np.ndarray], float]:
    """Masses by cluster, subspace and component, and the objective: tasks add up their own, Spark the tasks'."""
    cols, tables, k = _cells(grid, centroids.comps), centroids.distances(p), centroids.k
    sizes = [s.size for s in centroids.comps.subspaces]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total, cost = [np.zeros((k, n)) for n in sizes], 0.0
        for b in batches:
            cells, w = np.stack([b.column(c).to_numpy() for c in cols], 1).astype(int), b.column("w").to_numpy().astype(float)
            a, d = _sweep(cells, w, tables)
            cost += float((w * d).sum())
            for t, m in zip(total, _masses(cells, w, a, k, sizes), strict=True):
                t += m
        flat = np.concatenate([[cost], *[t.ravel() for t in total]])
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(flat), dtype=np.int32)), pa.array(flat)], ["i", "v"])

    rows = grid.select(*cols, "w").mapInArrow(run, "i int, v double").groupBy("i").agg(F.sum("v").alias("v")).toArrow()  # 1 + k * sum(sizes) rows
    flat = np.zeros(1 + k * sum(sizes))
    flat[rows.column("i").to_numpy()] = rows.column("v").to_numpy()
    out, at = [], 1
    for n in sizes:
        out.append(flat[at : at + k * n].reshape(k, n))
        at += k * n
    return out, float(flat[0])


def update(comps: ComponentSet, old: Centroids, mass: list[np.ndarray], p: int = 2, penalty: Penalty | None = None) -> Centroids:
    """New centroids from masses. An empty cluster stays. p = 1 takes medians; a penalty shrinks (see Penalty)."""
    total = mass[0].sum(1)
    out = []
    for j, s in enumerate(comps.subspaces):
        a = np.where(total[:, None] > 0, mass[j] / np.maximum(total, 1e-300)[:, None], old.coef[j])
        if p == 1 and s.heavy is None:
            order = np.argsort(s.centers, kind="stable")
            half = (np.cumsum(a[:, order], 1) >= 0.5 * a.sum(1, keepdims=True) - 1e-15).argmax(1)
            a = np.where(total[:, None] > 0, np.eye(s.size)[order[half]], old.coef[j])
        elif p == 1:
            a = np.where(total[:, None] > 0, (a > 0.5).astype(float), old.coef[j])
        if penalty is not None:
            a = np.where(total[:, None] > 0, shrunk(s, a, total, penalty), old.coef[j])
        out.append(a)
    return Centroids(comps, out)


def shrunk(s: Subspace, a: np.ndarray, total: np.ndarray, penalty: Penalty) -> np.ndarray:
    """The proximal step for each cluster's part: soft thresholds for numbers (l1), scaled vectors (group). Categories know group only."""
    t = penalty.lam / (2 * np.maximum(total, 1e-300) * s.feature.scale**2)
    if s.heavy is None:
        m = a @ s.centers
        factor = np.divide(np.sign(m) * np.maximum(np.abs(m) - t, 0), m, out=np.zeros_like(m), where=m != 0)
    elif penalty.kind == "group":
        norms = np.ones(a.shape[1])
        if s.has_light:
            norms[len(s.heavy)] = s.sqnorm
        size = np.sqrt((a * a * norms).sum(1))
        factor = np.maximum(1 - t / np.maximum(size, 1e-300), 0)
    else:
        # Along a component of squared norm q the best share moves by t / q; a light one's is under 1.
        norms = np.ones(a.shape[1])
        if s.has_light:
            norms[len(s.heavy)] = max(s.sqnorm, 1e-300)
        return np.maximum(a - t[:, None] / norms, 0)
    return a * factor[:, None]


def penalty_of(c: Centroids, penalty: Penalty) -> float:
    out = 0.0
    for j, s in enumerate(c.comps.subspaces):
        if s.heavy is None:
            out += penalty.lam * float(np.abs(c.value(j)).sum())
        else:
            norms = np.ones(c.coef[j].shape[1])
            if s.has_light:
                norms[len(s.heavy)] = s.sqnorm
            out += penalty.lam * float(np.sqrt((c.coef[j] ** 2 * norms).sum(1)).sum() if penalty.kind == "group" else c.coef[j].sum())
    return out


@dataclass
class Clustering:
    centroids: Centroids
    objective: float
    history: list[float]


def grid_lloyd(grid: DataFrame, comps: ComponentSet, seeds: np.ndarray, max_iter: int = 20, tol: float = 1e-4, p: int = 2, penalty: Penalty | None = None, local: bool | None = None) -> Clustering:
    """Lloyd on the cells from seed cells. A small grid comes to the driver once; a large one is swept by tasks.

    Stops after max_iter sweeps or when the objective falls by less than tol of itself; with tol = 0 all
    sweeps are made, as cells of a tie may still move. Ties go to the smallest cluster id. The last
    objective is that of the returned centroids.
    """
    now, history = point_mixtures(comps, seeds), []
    sizes, cols = [s.size for s in comps.subspaces], _cells(grid, comps)
    if local is None:
        local = grid.count() * len(cols) <= LOCAL_MOST
    if local:
        held = grid.select(*cols, "w").toArrow()
        cells, w = np.stack([held.column(c).to_numpy() for c in cols], 1).astype(int), held.column("w").to_numpy().astype(float)

    def sweep(c):
        if not local:
            return _pass(grid, c, p)
        a, d = _sweep(cells, w, c.distances(p))
        return _masses(cells, w, a, c.k, sizes), float((w * d).sum())

    for _ in range(max_iter):
        mass, cost = sweep(now)
        history.append(cost + (penalty_of(now, penalty) if penalty else 0.0))
        now = update(comps, now, mass, p, penalty)
        if tol > 0 and len(history) > 1 and history[-2] - history[-1] <= tol * abs(history[-2]):
            break
    _, cost = sweep(now)
    history.append(cost + (penalty_of(now, penalty) if penalty else 0.0))
    return Clustering(now, history[-1], history)
