"""Join trees, decompositions of cyclic queries, and width parameters, all on the driver."""

from __future__ import annotations

from dataclasses import dataclass, replace
from fractions import Fraction
from functools import lru_cache

from pyspark.sql import functions as F

from .spec import Edge, FeatureQuery


@dataclass
class JoinTree:
    """children[v]: edges oriented from v to its children; order visits parents first."""

    root: str
    children: dict[str, list[Edge]]
    order: list[str]

    def parent(self, v: str) -> Edge | None:
        return next((e for es in self.children.values() for e in es if e.right == v), None)


def join_tree(query: FeatureQuery) -> JoinTree:
    """The tree from the query's root; raises ValueError for a cycle, an unconnected relation or a left edge pointing to the root."""
    if len(query.edges) != len(query.relations) - 1:
        raise ValueError(f"{query.name}: {len(query.edges)} edges over {len(query.relations)} relations are no tree; decompose it first")
    children: dict[str, list[Edge]] = {r: [] for r in query.relations}
    order, seen = [query.root], {query.root}
    for v in order:
        for e in query.edges:
            w = e.right if e.left == v else e.left if e.right == v else None
            if w is None or w in seen:
                continue
            if e.left != v:
                if e.how != "inner":
                    raise ValueError(f"{query.name}: the left join {e.left}-{e.right} must point away from the root")
                e = Edge(v, w, tuple((b, a) for a, b in e.on))
            children[v].append(e)
            seen.add(w)
            order.append(w)
    if seen != set(query.relations):
        raise ValueError(f"{query.name}: not all relations are connected")
    return JoinTree(query.root, children, order)


def cycle(query: FeatureQuery) -> list[str]:
    """Relations left after taking off those with one neighbour, again and again: empty for a tree."""
    left, edges = set(query.relations), list(query.edges)
    while True:
        ends = [r for r in left if sum(r in (e.left, e.right) for e in edges) <= 1]
        if not ends:
            return [r for r in query.relations if r in left]
        left -= set(ends[:1])
        edges = [e for e in edges if ends[0] not in (e.left, e.right)]


def decompose(query: FeatureQuery, bag: str = "bag") -> FeatureQuery:
    """A tree query of the same rows: the relations on cycles become one counted relation.

    Each relation enters the bag with its keys and feature values alone, pre-counted, so the bag has
    a row per combination that occurs, never a copy of the joined rows.
    """
    core = cycle(query)
    if not core:
        return query
    inner = [e for e in query.edges if e.left in core and e.right in core]
    outer = [e for e in query.edges if e not in inner]
    if any(e.how != "inner" for e in inner):
        raise ValueError("left joins on a cycle are not known")
    name = lambda r, col: f"{r}__{col}"
    parts = {}
    for r in core:
        cols = [F.col(k).alias(name(r, k)) for k in query.keys(r)] + [f.column().alias(f"f__{f.name}") for f in query.of(r)]
        keys = [name(r, k) for k in query.keys(r)] + [f"f__{f.name}" for f in query.of(r)]
        w = "__w" if "__w" in query.relations[r].columns else None
        parts[r] = query.relations[r].select(*cols, F.col(w).alias(f"{r}__n") if w else F.lit(1).cast("long").alias(f"{r}__n")).groupBy(*keys).agg(F.sum(f"{r}__n").alias(f"{r}__n"))
    done, df, left = [core[0]], parts[core[0]], list(inner)
    while len(done) < len(core):
        r = next(x for x in core if x not in done and any({x, d} == {e.left, e.right} for e in left for d in done))
        on = [(name(e.left, a), name(e.right, b)) for e in left if r in (e.left, e.right) and (e.left in done or e.right in done) for a, b in e.on]
        cond = [F.col(a) == F.col(b) for a, b in on]
        joined = cond[0]
        for x in cond[1:]:
            joined = joined & x
        df = df.join(parts[r], joined)
        left = [e for e in left if not (r in (e.left, e.right) and (e.left in done or e.right in done))]
        done.append(r)
    keep = [name(r, a) for e in outer for r, a in [(x, y) for x, ys in ((e.left, [p for p, _ in e.on]), (e.right, [p for _, p in e.on])) if x in core for y in ys]]
    feats = [f"f__{f.name}" for r in core for f in query.of(r)]
    weight = F.lit(1).cast("long")
    for r in core:
        weight = weight * F.col(f"{r}__n")
    df = df.groupBy(*dict.fromkeys([*keep, *feats])).agg(F.sum(weight).alias("__w"))
    features = [replace(f, relation=bag, expr=f"`f__{f.name}`", decimals=None) if f.relation in core else f for f in query.features]
    edges = []
    for e in outer:
        left_, right = (bag if x in core else x for x in (e.left, e.right))
        edges.append(Edge(left_, right, tuple((name(e.left, a) if e.left in core else a, name(e.right, b) if e.right in core else b) for a, b in e.on), e.how))
    relations = {bag: df} | {r: d for r, d in query.relations.items() if r not in core}
    return FeatureQuery(query.name, relations, edges, features, bag if query.root in core else query.root, query.chains)


# ---- widths -------------------------------------------------------------------------------------


@dataclass(frozen=True)
class Hypergraph:
    """Attributes of a join, and for each relation those it has."""

    edges: tuple[frozenset[str], ...]

    @classmethod
    def of(cls, *edges) -> Hypergraph:
        return cls(tuple(frozenset(e) for e in edges))

    @classmethod
    def of_query(cls, query: FeatureQuery) -> Hypergraph:
        """Join columns that edges equate are one attribute; a relation's other columns are an attribute of its own."""
        group: dict[tuple[str, str], tuple[str, str]] = {}

        def top(x):
            while group.setdefault(x, x) != x:
                x = group[x]
            return x

        for e in query.edges:
            for a, b in e.on:
                group[top((e.left, a))] = top((e.right, b))
        return cls.of(*[{"/".join(top((r, k))) for k in query.keys(r)} | {f"{r}.*"} for r in query.relations])

    @property
    def vertices(self) -> frozenset[str]:
        return frozenset().union(*self.edges)


def packing(rows: list[list[int]], n: int) -> Fraction:
    """max sum(x) with rows . x <= 1, x >= 0, exactly: a simplex with Bland's rule on fractions."""
    m = len(rows)
    t = [[Fraction(v) for v in r] + [Fraction(int(i == j)) for j in range(m)] + [Fraction(1)] for i, r in enumerate(rows)]
    z = [Fraction(-1)] * n + [Fraction(0)] * (m + 1)
    basis = [n + i for i in range(m)]
    while True:
        j = next((j for j in range(n + m) if z[j] < 0), None)
        if j is None:
            return z[-1]
        ratio = [(t[i][-1] / t[i][j], basis[i], i) for i in range(m) if t[i][j] > 0]
        if not ratio:
            raise ValueError("an attribute is in no relation")
        i = min(ratio)[2]
        p = t[i][j]
        t[i] = [v / p for v in t[i]]
        for r in [*(t[k] for k in range(m) if k != i), z]:
            if r[j]:
                f = r[j]
                r[:] = [a - f * b for a, b in zip(r, t[i], strict=True)]
        basis[i] = j


def rho_star(h: Hypergraph, over: frozenset[str] | None = None) -> Fraction:
    """The fractional edge cover number of some attributes (of all), by its dual."""
    over = h.vertices if over is None else over
    if not over:
        return Fraction(0)
    order = sorted(over)
    return packing([[int(v in e) for v in order] for e in h.edges if e & over], len(order))


def agm_bound(h: Hypergraph, n: int) -> float:
    """The most rows that the join can have with n rows in each relation."""
    return float(n) ** float(rho_star(h))


def fhtw(h: Hypergraph) -> Fraction:
    """The fractional hypertree width: the least, over elimination orders, of the greatest cover number of a bag."""
    verts = [v for v in sorted(h.vertices) if sum(v in e for e in h.edges) > 1]
    alone = max((rho_star(h, e) for e in h.edges), default=Fraction(0))

    @lru_cache(maxsize=None)
    def reach(v: str, gone: frozenset[str]) -> frozenset[str]:
        """v, and the attributes it meets once those in gone are eliminated."""
        out, todo, seen = {v}, [v], {v}
        while todo:
            x = todo.pop()
            for e in h.edges:
                if x in e:
                    for y in e:
                        if y in gone and y not in seen:
                            seen.add(y)
                            todo.append(y)
                        elif y not in gone and y in verts:
                            out.add(y)
        return frozenset(out)

    @lru_cache(maxsize=None)
    def best(gone: frozenset[str]) -> Fraction:
        left = [v for v in verts if v not in gone]
        if not left:
            return Fraction(0)
        return min(max(rho_star(h, reach(v, gone)), best(gone | {v})) for v in left)

    return max(alone, best(frozenset()))


def gap_exponent(h: Hypergraph) -> Fraction:
    """How many powers of the relation size the method saves over building the matrix."""
    return rho_star(h) - max(fhtw(h), Fraction(2))
