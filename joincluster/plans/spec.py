"""A feature query: relations, the equi-joins between them, and the features of its rows."""

from __future__ import annotations

from dataclasses import dataclass, field, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: The category of a null.
MISSING = "∅"


@dataclass(frozen=True)
class Feature:
    """One feature, an SQL expression over one relation. scale weighs its subspace; default stands in for rows without a
    partner under a left join; decimals rounds first; category_scale weighs single categories."""

    name: str
    relation: str
    expr: str
    kind: str = "cat"
    scale: float = 1.0
    default: float | str | None = None
    decimals: int | None = None
    category_scale: tuple[tuple[str, float], ...] = ()

    def column(self) -> Column:
        c = F.expr(self.expr)
        if self.kind == "cat":
            return F.coalesce(c.cast("string"), F.lit(MISSING))
        c = c.cast("double")
        return F.round(c, self.decimals) if self.decimals is not None else c

    def fallback(self):
        if self.default is not None:
            return str(self.default) if self.kind == "cat" else float(self.default)
        return MISSING if self.kind == "cat" else 0.0


@dataclass(frozen=True)
class Edge:
    """An equi-join of two relations; on holds column pairs. A left edge keeps rows of left without a partner."""

    left: str
    right: str
    on: tuple[tuple[str, str], ...]
    how: str = "inner"


@dataclass
class FeatureQuery:
    name: str
    relations: dict[str, DataFrame]
    edges: list[Edge]
    features: list[Feature]
    root: str
    chains: list[list[str]] = field(default_factory=list)

    def validate(self) -> FeatureQuery:
        for e in self.edges:
            for r, cols in ((e.left, [a for a, _ in e.on]), (e.right, [b for _, b in e.on])):
                missing = set(cols) - set(self.relations[r].columns)
                if missing:
                    raise ValueError(f"{self.name}: {r} has no columns {sorted(missing)}")
            if e.how not in ("inner", "left"):
                raise ValueError(f"{self.name}: {e.how} joins are not known")
        names = [f.name for f in self.features]
        if len(set(names)) != len(names):
            raise ValueError(f"{self.name}: features repeat")
        for f in self.features:
            if f.relation not in self.relations or f.kind not in ("cat", "cont"):
                raise ValueError(f"{self.name}: feature {f.name} is not sound")
        return self

    def feature(self, name: str) -> Feature:
        return next(f for f in self.features if f.name == name)

    def of(self, relation: str) -> list[Feature]:
        return [f for f in self.features if f.relation == relation]

    def keys(self, relation: str) -> list[str]:
        out = [a for e in self.edges if e.left == relation for a, _ in e.on] + [b for e in self.edges if e.right == relation for _, b in e.on]
        return list(dict.fromkeys(out))

    def only(self, *names: str) -> FeatureQuery:
        return replace(self, features=[f for f in self.features if f.name in names], chains=[[x for x in ch if x in names] for ch in self.chains])

    @classmethod
    def from_views(cls, spark, name: str, views: dict[str, str], edges: list[Edge], features: list[Feature], root: str, **more) -> FeatureQuery:
        """A query whose relations are SQL texts over registered views."""
        return cls(name, {k: spark.sql(v) for k, v in views.items()}, edges, features, root, **more).validate()
