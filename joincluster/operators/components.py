"""Components of all subspaces: what the driver keeps of them, and the columns that encode values."""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.spec import Feature, FeatureQuery
from .categorical import heavy_light, heavy_light_local
from .line import BUCKETS, Line, line_kmeans


@dataclass
class Subspace:
    """One feature's components. Numbers: centers and upper ends. Categories: heavy ones, then one light (light > 0)."""

    feature: Feature
    mass: np.ndarray
    cost: float
    centers: np.ndarray | None = None
    upper: np.ndarray | None = None
    heavy: list[str] | None = None
    sqnorm: float = 0.0
    exact: bool = True  # whether the solver is known to be optimal

    @property
    def name(self) -> str:
        return self.feature.name

    @property
    def size(self) -> int:
        return len(self.mass)

    @property
    def has_light(self) -> bool:
        return self.heavy is not None and self.size > len(self.heavy)

    def encode(self, column: Column | None = None) -> Column:
        """The component of a value: by segment ends, or by a look-up among the heavy categories. Unseen categories are light."""
        c = F.col(f"f__{self.name}") if column is None else column
        if self.heavy is None:
            if self.size <= 1:
                return F.lit(0)
            out = F.when(c <= F.lit(float(self.upper[0])), F.lit(0))
            for i, h in enumerate(self.upper[1:-1], 1):
                out = out.when(c <= F.lit(float(h)), F.lit(i))
            return out.otherwise(F.lit(self.size - 1))
        if not self.heavy:
            return F.lit(0)
        at = F.array_position(F.array(*[F.lit(h) for h in self.heavy]), c)
        return F.when(at > 0, (at - 1).cast("int")).otherwise(F.lit(len(self.heavy) if self.has_light else 0))

    def of_value(self, value) -> int:
        if self.heavy is None:
            return int(min(np.searchsorted(self.upper, float(value), "left"), self.size - 1))
        return self.heavy.index(value) if value in self.heavy else (len(self.heavy) if self.has_light else 0)


@dataclass
class ComponentSet:
    query: FeatureQuery
    subspaces: list[Subspace]

    def __getitem__(self, name: str) -> Subspace:
        return next(s for s in self.subspaces if s.name == name)

    @property
    def encoders(self) -> dict[str, Column]:
        return {s.name: s.encode() for s in self.subspaces}

    @property
    def defaults(self) -> dict[str, int]:
        return {s.name: s.of_value(s.feature.fallback()) for s in self.subspaces}

    @property
    def cost(self) -> float:
        """The cost of moving every row to its cell: the sum of the subspaces' own costs."""
        return sum(s.cost * s.feature.scale**2 for s in self.subspaces)

    def table(self, spark: SparkSession) -> DataFrame:
        """subspace, comp, kind, center, hi, cat, mass, sqnorm."""
        rows = []
        for s in self.subspaces:
            for i in range(s.size):
                if s.heavy is None:
                    rows.append((s.name, i, "segment", float(s.centers[i]), float(s.upper[i]), None, float(s.mass[i]), float(s.centers[i] ** 2)))
                elif i < len(s.heavy):
                    rows.append((s.name, i, "heavy", None, None, s.heavy[i], float(s.mass[i]), 1.0))
                else:
                    rows.append((s.name, i, "light", None, None, None, float(s.mass[i]), float(s.sqnorm)))
        return spark.createDataFrame(rows, "subspace string, comp int, kind string, center double, hi double, cat string, mass double, sqnorm double")


def kappa_of(kappa: int | dict[str, int], name: str) -> int:
    return kappa[name] if isinstance(kappa, dict) else kappa


def bisect(edges: Column, value: Column, n: int) -> Column:
    """How many of n sorted edges are below value: log2(n) steps of one array look-up each."""
    at = F.lit(0)
    steps = F.array(*[F.lit(1 << i) for i in range(max(1, n).bit_length() - 1, -1, -1)])
    return F.aggregate(steps, at, lambda a, s: F.when((a + s <= n) & (F.try_element_at(edges, F.least(a + s, F.lit(n))) < value), a + s).otherwise(a))


def bucketed(marginal: DataFrame, buckets: int = BUCKETS) -> DataFrame:
    """vnum, w, inner, hi of a numeric marginal: itself where it is small enough, else equal-mass buckets with their mean, mass and inner spread.

    The bucket edges come from a sketch, so a task never holds a feature's values.
    """
    n = marginal.count()
    if n <= buckets:
        return marginal.select("vnum", "w", F.lit(0.0).alias("inner"), F.col("vnum").alias("hi"))
    edges = marginal.agg(F.percentile_approx("vnum", [i / buckets for i in range(1, buckets)], 10 * buckets)).first()[0]
    # A value's bucket is the number of edges below it, found among its equal-width neighbours' edges by a binary search over one array.
    held = F.array(*[F.lit(float(e)) for e in sorted(set(edges))])
    keyed = marginal.where("w > 0").crossJoin(F.broadcast(marginal.sparkSession.range(1).select(held.alias("edges")))).withColumn("b", bisect(F.col("edges"), F.col("vnum"), len(set(edges)))).drop("edges")
    w = F.col("w").cast("double")
    g = keyed.groupBy("b").agg(F.sum(w).alias("w"), F.sum(w * F.col("vnum")).alias("s"), F.sum(w * F.col("vnum") * F.col("vnum")).alias("q"), F.max("vnum").alias("hi"))
    return g.select((F.col("s") / F.col("w")).alias("vnum"), "w", F.greatest(F.col("q") - F.col("s") * F.col("s") / F.col("w"), F.lit(0.0)).alias("inner"), "hi")


#: Rows of all marginals together that the driver solves in one go.
MARGINALS_LOCAL = 1 << 18


def _line_of(rows, kappa: int, method: str, p: int, lam: float) -> tuple[Line, bool]:
    """The segments of rows (vnum, w, inner, hi; pandas), and whether they are the best ones of the values themselves."""
    line = line_kmeans(rows["vnum"], rows["w"].astype(float), kappa, method, p, lam, rows["inner"])
    spread = bool((rows["inner"] > 0).any())
    if len(line.upper) and spread:
        order = np.sort(rows["vnum"].to_numpy())
        tops = rows.set_index("vnum")["hi"].reindex(order).to_numpy()
        line.upper = tops[np.searchsorted(order, line.upper, "right") - 1]
    return line, method != "lloyd" and not spread


def solve_line(marginal: DataFrame, kappa: int, method: str = "auto", p: int = 2, lam: float = 0.0, buckets: int = BUCKETS) -> Line:
    """The numeric subspace of a marginal (vnum, w); nulls are the value 0."""
    return _line_of(_line_rows(marginal, buckets), kappa, method, p, lam)[0]


def _line_rows(marginal: DataFrame, buckets: int = BUCKETS):
    return bucketed(marginal.select(F.coalesce("vnum", F.lit(0.0)).alias("vnum"), "w").groupBy("vnum").agg(F.sum("w").alias("w")), buckets).toPandas()


def solve(query: FeatureQuery, marginals: DataFrame, kappa: int | dict[str, int], method: str = "auto", p: int = 2, lam: float = 0.0) -> ComponentSet:
    """Components of every feature from its marginal.

    Marginals of MARGINALS_LOCAL rows in all come to the driver in one job. Larger ones are solved a
    feature at a time: at most BUCKETS rows a number and kappa a category reach the driver.
    """
    held = marginals.select("subspace", "vnum", "vcat", F.col("w").cast("double").alias("w")).limit(MARGINALS_LOCAL + 1).toPandas()
    parts = dict(tuple(held.groupby("subspace"))) if len(held) <= MARGINALS_LOCAL else None
    out = []
    for f in query.features:
        m, k = marginals.where(F.col("subspace") == f.name), kappa_of(kappa, f.name)
        mine = held.iloc[:0] if parts is None else parts.get(f.name, held.iloc[:0])
        if f.kind == "cont":
            if parts is not None and len(mine) <= BUCKETS:
                rows = mine.assign(vnum=mine["vnum"].fillna(0.0), inner=0.0, hi=mine["vnum"].fillna(0.0))
            else:
                rows = _line_rows(m)
            line, exact = _line_of(rows, k, method, p, lam)
            out.append(Subspace(f, line.mass, line.cost, line.centers, line.upper, exact=exact))
        else:
            h = heavy_light(m, k) if parts is None else heavy_light_local(list(zip(mine["vcat"], mine["w"], strict=True)), k)
            mass = [w for _, w in h.heavy] + ([h.light] if h.light > 0 else [])
            out.append(Subspace(f, np.array(mass), h.cost if p == 2 else h.median_cost, heavy=[c for c, _ in h.heavy], sqnorm=h.sqnorm))
    return ComponentSet(query, out)


def cell_key(names: list[str], sizes: list[int]) -> Column:
    """A cell's ids packed into one number, where the product of the sizes allows."""
    if int(np.prod([float(s) for s in sizes])) >= 1 << 62:
        raise ValueError("too many cells for one number")
    return reduce(lambda a, b: a * b[1] + F.col(b[0]), list(zip(names, sizes, strict=True))[1:], F.col(names[0]).cast("bigint"))
