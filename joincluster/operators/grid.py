"""The grid coreset: its non-empty cells and their row counts."""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.messages import Calibration
from ..plans.spec import FeatureQuery
from .baseline import materialise
from .components import ComponentSet


def grid_weights(query: FeatureQuery, comps: ComponentSet, weight: str = "bigint", chains: dict[str, DataFrame] | None = None) -> DataFrame:
    """c_<feature>..., w over the join tree, never over the joined rows.

    chains (name to a table of its cells, as fd.chain_cells makes it) adds a column k_<name> with the
    chain's one cell number, in place of its features' columns.
    """
    cells = Calibration(query, weight).grid(comps.encoders, comps.defaults)
    for name, ids in (chains or {}).items():
        on = [c for c in ids.columns if c.startswith("c_")]
        cells = cells.join(F.broadcast(ids), on).drop(*on).withColumnRenamed("cell", f"k_{name}")
    return cells


def grid_weights_flat(query: FeatureQuery, comps: ComponentSet, build: Callable[[FeatureQuery], DataFrame] = materialise) -> DataFrame:
    """The same by its definition: encode every joined row and count. build=baseline.counted encodes equal rows once."""
    x = build(query)
    names = [f.name for f in query.features]
    cols = [comps[n].encode(F.col(n)).alias(f"c_{n}") for n in names]
    return x.select(*cols, "w").groupBy(*[f"c_{n}" for n in names]).agg(F.sum("w").cast("bigint").alias("w"))


def full_grid(spark, comps: ComponentSet) -> DataFrame:
    """Every cell of the product of the components. Only for small products: there are kappa^m of them."""
    parts = [spark.range(s.size).select(F.col("id").cast("int").alias(f"c_{s.name}")) for s in comps.subspaces]
    return reduce(lambda a, b: a.crossJoin(F.broadcast(b)), parts)


def grid_zero_fill(left: DataFrame, right: DataFrame, observed: DataFrame, value_of, zero: int) -> DataFrame:
    """Cells of left x right with a measure that is 0 for pairs that are not observed, without the product of rows.

    left (key l, cell columns), right (key r, cell columns), observed (l, r, value). value_of encodes
    the value column, zero is the component of 0. A pair of cells has n_left * n_right row pairs; the
    observed ones are counted, the rest belong to zero.
    """
    lc, rc = ([c for c in df.columns if c.startswith("c_")] for df in (left, right))
    seen = observed.join(left, "l").join(right, "r").select(*lc, *rc, value_of.alias("c_value")).groupBy(*lc, *rc, "c_value").agg(F.count("*").alias("w"))
    a = left.groupBy(*lc).agg(F.count("*").alias("n_l"))
    b = right.groupBy(*rc).agg(F.count("*").alias("n_r"))
    used = seen.groupBy(*lc, *rc).agg(F.sum("w").alias("used"))
    # The product is of cells, whose number the components bound, not of rows.
    rest = a.crossJoin(F.broadcast(b)).join(used, [*lc, *rc], "left").select(*lc, *rc, F.lit(zero).alias("c_value"), (F.col("n_l") * F.col("n_r") - F.coalesce("used", F.lit(0))).alias("w"))
    return seen.unionByName(rest.where("w > 0")).groupBy(*lc, *rc, "c_value").agg(F.sum("w").alias("w"))


def grid_summary(cells: DataFrame, comps: ComponentSet, expand: str = "ids") -> DataFrame:
    """The cells as weighted points for other learners: component ids, or with expand='centers' the components' centers (numbers) and categories."""
    if expand == "ids":
        return cells
    out = []
    for s in comps.subspaces:
        names = F.array(*[F.lit(h) for h in s.heavy], F.lit("*")) if s.heavy is not None else F.array(*[F.lit(float(x)) for x in s.centers])
        out.append(F.element_at(names, F.col(f"c_{s.name}") + 1).alias(s.name))
    return cells.select(*out, "w")


def pick_kappa(query: FeatureQuery, marginals: DataFrame, budget: int, kappas: tuple[int, ...] = (50, 20, 10, 5, 2)) -> int:
    """The greatest kappa whose cells fit the budget, by an approximate count of each grid's cells."""
    from .components import solve

    for k in kappas:
        cells = grid_weights(query, solve(query, marginals, k))
        if cells.select(F.approx_count_distinct(F.struct(*[c for c in cells.columns if c != "w"]))).first()[0] <= budget:
            return k
    return kappas[-1]
