"""Counts pushed below the joins: messages over a join tree, marginals and the grid from them.

A relation sends its neighbour one row per join key with the number of joined rows behind it, so
what is shuffled has the size of the keys, never that of the joined matrix. Catalyst does not move
aggregates below joins; these plans do.
"""

from __future__ import annotations

from functools import cached_property, reduce

from pyspark import StorageLevel
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .hypergraph import JoinTree, decompose, join_tree
from .spec import Edge, FeatureQuery


def product(columns: list[Column]) -> Column:
    return reduce(lambda a, b: a * b, columns)


class Calibration:
    """Up and down messages of a query. weight is 'bigint', or 'decimal(38,0)' where the joined rows may pass 2^63."""

    def __init__(self, query: FeatureQuery, weight: str = "bigint"):
        self.query = decompose(query.validate())
        self.weight = weight
        self.tree: JoinTree = join_tree(self.query)
        self._up: dict[str, DataFrame] = {}
        self._down: dict[str, DataFrame] = {}
        self._held: list[DataFrame] = []

    def _hold(self, df: DataFrame) -> DataFrame:
        self._held.append(df.persist(StorageLevel.MEMORY_AND_DISK))
        return self._held[-1]

    def release(self) -> None:
        for df in self._held:
            df.unpersist()
        self._held.clear()

    def base(self, v: str) -> DataFrame:
        """Relation v with its keys, its features (f__name) and __w, nothing else: the scan reads only those."""
        df = self.query.relations[v]
        w = F.col("__w") if "__w" in df.columns else F.lit(1)
        return df.select(*self.query.keys(v), *[f.column().alias(f"f__{f.name}") for f in self.query.of(v)], w.cast(self.weight).alias("__w"))

    def _send(self, df: DataFrame, keys: list[str], to: str) -> DataFrame:
        """Rows of df as a message: a row a key, named apart by its receiver's side. Null keys join nothing."""
        keyed = df.where(reduce(lambda a, b: a & b, [F.col(k).isNotNull() for k in keys]))
        return keyed.groupBy(*[F.col(k).alias(f"{to}__{i}") for i, k in enumerate(keys)]).agg(F.sum("__w").cast(self.weight).alias(f"{to}__w"))

    def _take(self, df: DataFrame, message: DataFrame, keys: list[str], name: str, how: str = "inner") -> DataFrame:
        """df with the message's count multiplied in; a left edge counts 1 where there is no partner."""
        on = reduce(lambda a, b: a & b, [F.col(k) == F.col(f"{name}__{i}") for i, k in enumerate(keys)])
        got = df.join(message, on, how)
        count = F.coalesce(f"{name}__w", F.lit(1)) if how == "left" else F.col(f"{name}__w")
        return got.withColumn("__w", (F.col("__w") * count).cast(self.weight)).drop(f"{name}__w", *[f"{name}__{i}" for i in range(len(keys))])

    def _gathered(self, v: str, without: str | None = None) -> DataFrame:
        df = self.base(v)
        for e in self.tree.children[v]:
            if e.right != without:
                df = self._take(df, self.up(e), [a for a, _ in e.on], f"u_{e.right}", e.how)
        return df

    def up(self, e: Edge) -> DataFrame:
        """What the subtree of e.right sends to e.left."""
        if e.right not in self._up:
            self._up[e.right] = self._hold(self._send(self._gathered(e.right), [b for _, b in e.on], f"u_{e.right}"))
        return self._up[e.right]

    def _with_down(self, v: str, df: DataFrame) -> DataFrame:
        e = self.tree.parent(v)
        return df if e is None else self._take(df, self.down(e), [b for _, b in e.on], f"d_{v}")

    def down(self, e: Edge) -> DataFrame:
        """What the rest of the query sends to e.right through e.left."""
        if e.right not in self._down:
            rest = self._with_down(e.left, self._gathered(e.left, without=e.right))
            self._down[e.right] = self._hold(self._send(rest, [a for a, _ in e.on], f"d_{e.right}"))
        return self._down[e.right]

    def rows_of(self, v: str) -> DataFrame:
        """Relation v, each row with the number of joined rows it is part of. Rows in none are gone."""
        return self._with_down(v, self._gathered(v))

    @cached_property
    def size(self) -> int:
        """The number of joined rows."""
        return int(self._gathered(self.tree.root).agg(F.sum("__w")).first()[0] or 0)

    def _unmatched(self, v: str) -> DataFrame | None:
        """Joined rows that lack v (one row, n), for v below a left edge; None where there can be none."""
        path, x = [], v
        while (e := self.tree.parent(x)) is not None:
            path.append(e)
            x = e.left
        lefts = [e for e in path if e.how == "left"]
        if not lefts:
            return None
        out = []
        for e in lefts:
            rest = self._with_down(e.left, self._gathered(e.left, without=e.right))
            on = reduce(lambda a, b: a & b, [F.col(a) == F.col(f"u_{e.right}__{i}") for i, (a, _) in enumerate(e.on)])
            out.append(rest.join(self.up(e), on, "left_anti").agg(F.coalesce(F.sum("__w"), F.lit(0)).cast(self.weight).alias("n")))
        return reduce(DataFrame.unionByName, out)

    def marginal(self, name: str) -> DataFrame:
        """subspace, vnum, vcat, w of one feature."""
        return self._marginals_of(self.query.feature(name).relation, [name])

    def _marginals_of(self, v: str, names: list[str]) -> DataFrame:
        feats = [self.query.feature(n) for n in names]
        cells = F.array(*[
            F.struct(F.lit(f.name).alias("subspace"), (F.col(f"f__{f.name}") if f.kind == "cont" else F.lit(None)).cast("double").alias("vnum"), (F.col(f"f__{f.name}") if f.kind == "cat" else F.lit(None)).cast("string").alias("vcat"))
            for f in feats
        ])
        df = self.rows_of(v).groupBy(*[f"f__{n}" for n in names]).agg(F.sum("__w").alias("__w")).select(F.explode(cells).alias("x"), "__w").select("x.*", "__w")
        lacking = self._unmatched(v)
        if lacking is not None:
            default = F.array(*[F.struct(F.lit(f.name).alias("subspace"), F.lit(f.fallback() if f.kind == "cont" else None).cast("double").alias("vnum"), F.lit(f.fallback() if f.kind == "cat" else None).cast("string").alias("vcat")) for f in feats])
            df = df.unionByName(lacking.where("n > 0").select(F.explode(default).alias("x"), F.col("n").alias("__w")).select("x.*", "__w"))
        return df.groupBy("subspace", "vnum", "vcat").agg(F.sum("__w").cast(self.weight).alias("w"))

    def marginals(self) -> DataFrame:
        """All features' marginals: two messages an edge serve every feature."""
        by = {}
        for f in self.query.features:
            by.setdefault(f.relation, []).append(f.name)
        return reduce(DataFrame.unionByName, [self._marginals_of(v, names) for v, names in by.items()])

    def grid(self, encode: dict[str, Column], defaults: dict[str, int], keep: dict[str, Column] | None = None) -> DataFrame:
        """c_<feature>..., w: the non-empty cells. encode maps f__<feature> to its component; defaults are those of rows without a partner.

        Values become component ids in their own relation, which is counted before any join; every key
        is summed out as soon as its last join is done. keep adds raw columns (name to expression).
        """
        keep = keep or {}

        def fold(v: str) -> tuple[DataFrame, list[str]]:
            feats = self.query.of(v)
            cells = [f"c_{f.name}" for f in feats]
            raw = [k for k in keep if any(f"f__{f.name}" in k or k == f"r_{f.name}" for f in feats)]
            keys = self.query.keys(v)
            df = self.base(v).select(*keys, *[encode[f.name].alias(f"c_{f.name}") for f in feats], *[keep[k].alias(k) for k in raw], "__w")
            cells = cells + raw
            df = df.groupBy(*keys, *cells).agg(F.sum("__w").cast(self.weight).alias("__w"))
            for e in self.tree.children[v]:
                below, names = fold(e.right)
                message = below.select(*[F.col(b).alias(f"m__{i}") for i, (_, b) in enumerate(e.on)], *names, F.col("__w").alias("m__w"))
                on = reduce(lambda a, b: a & b, [F.col(a) == F.col(f"m__{i}") for i, (a, _) in enumerate(e.on)])
                df = df.join(message, on, e.how)
                if e.how == "left":
                    df = df.withColumns({n: F.coalesce(n, F.lit(defaults.get(n[2:], 0))) for n in names if n.startswith("c_")})
                    df = df.withColumns({n: F.coalesce(n, F.lit(self.query.feature(n[2:]).fallback())) for n in names if n.startswith("r_")})
                    df = df.withColumn("m__w", F.coalesce("m__w", F.lit(1)))
                cells = cells + names
                done = [a for a, _ in e.on]
                later = [a for x in self.tree.children[v] if x is not e and self.tree.children[v].index(x) > self.tree.children[v].index(e) for a, _ in x.on]
                up = self.tree.parent(v)
                stay = [k for k in keys if k in later or (up and k in [b for _, b in up.on])]
                keys = [k for k in keys if k in stay or k not in done]
                df = df.withColumn("__w", (F.col("__w") * F.col("m__w")).cast(self.weight)).groupBy(*keys, *cells).agg(F.sum("__w").cast(self.weight).alias("__w"))
            up = self.tree.parent(v)
            mine = [b for _, b in up.on] if up else []
            return df.groupBy(*mine, *cells).agg(F.sum("__w").cast(self.weight).alias("__w")), cells

        df, cells = fold(self.tree.root)
        order = [f"c_{f.name}" for f in self.query.features]
        return df.select(*order, *[k for k in cells if k not in order], F.col("__w").alias("w"))
