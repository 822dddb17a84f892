"""Functional dependencies: checks, discovery, chains of features, and the cells that chains can have."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from ..plans.spec import FeatureQuery
from .components import ComponentSet


def fd_images(df: DataFrame, lhs: str, rhs: str) -> int:
    """The greatest number of values of rhs beside one value of lhs; 0 for an empty table. Counted by grouping twice, so hot values combine before the shuffle."""
    pairs = df.select(F.col(lhs).alias("a"), F.col(rhs).alias("b")).distinct()
    return int(pairs.groupBy("a").agg(F.count("*").alias("n")).agg(F.max("n")).first()[0] or 0)


def verify_fd(df: DataFrame, lhs: str, rhs: str) -> bool:
    return fd_images(df, lhs, rhs) <= 1


def fd_report(tables: dict[str, DataFrame], pairs: list[tuple[str, str, str]]) -> DataFrame:
    """relation, lhs, rhs, holds, max_images for each (relation, lhs, rhs)."""
    out = []
    for r, a, b in pairs:
        distinct = tables[r].select(F.col(a).alias("a"), F.col(b).alias("b")).distinct()
        images = distinct.groupBy("a").agg(F.count("*").alias("n")).agg(F.coalesce(F.max("n"), F.lit(0)).cast("bigint").alias("max_images"))
        out.append(images.select(F.lit(r).alias("relation"), F.lit(a).alias("lhs"), F.lit(b).alias("rhs"), (F.col("max_images") <= 1).alias("holds"), "max_images"))
    return reduce(DataFrame.unionByName, out)


def discover_fds(df: DataFrame, columns: list[str]) -> list[tuple[str, str]]:
    """All (a, b) of the columns with a determining b."""
    return [(a, b) for a in columns for b in columns if a != b and verify_fd(df, a, b)]


def chain_cover(fds: list[tuple[str, str]], features: list[str]) -> list[list[str]]:
    """Features in as few chains as can be, each from determining to determined; others stand alone.

    A minimum path cover of the closure of the dependencies, by bipartite matching; features that
    determine each other stand next to each other.
    """
    reach = {f: {b for a, b in fds if a == f and b in features} for f in features}
    for k in features:
        for a in features:
            if k in reach[a]:
                reach[a] |= reach[k]
    rank = {f: i for i, f in enumerate(features)}
    after = {f: [g for g in sorted(reach[f], key=lambda g: (-len(reach[g]), rank[g])) if g != f and (f not in reach[g] or rank[f] < rank[g])] for f in features}
    into: dict[str, str] = {}

    def place(f: str, seen: set[str]) -> bool:
        for g in after[f]:
            if g not in seen:
                seen.add(g)
                if g not in into or place(into[g], seen):
                    into[g] = f
                    return True
        return False

    for f in sorted(features, key=lambda f: (-len(after[f]), rank[f])):
        place(f, set())
    nxt = {a: b for b, a in into.items()}
    out = []
    for f in features:
        if f not in into:
            chain = [f]
            while chain[-1] in nxt:
                chain.append(nxt[chain[-1]])
            out.append(chain)
    return sorted(out, key=lambda ch: (-len(ch), rank[ch[0]]))


def chain_cells(values: DataFrame, comps: ComponentSet, chain: list[str]) -> DataFrame:
    """c_<feature>..., cell: the cells that the rows of values (columns named by feature) have in a chain, numbered from 0 by their ids."""
    cols = [f"c_{n}" for n in chain]
    cells = values.select(*[comps[n].encode(F.col(n)).alias(c) for n, c in zip(chain, cols, strict=True)]).distinct()
    # One row a cell, at most 1 + d (kappa - 1) of them: a single window over it is small whatever the data.
    return cells.withColumn("cell", (F.row_number().over(W.orderBy(*cols)) - 1).cast("int"))


def cell_bound(chains: list[list[str]], kappa: int) -> int:
    """The product over chains of 1 + length * (kappa - 1)."""
    return reduce(lambda a, c: a * (1 + len(c) * (kappa - 1)), chains, 1)


def chains_of(query: FeatureQuery) -> list[list[str]]:
    """The query's chains, and every other feature alone."""
    used = {f for ch in query.chains for f in ch}
    return [*[ch for ch in query.chains if ch], *[[f.name] for f in query.features if f.name not in used]]
