"""The classic way, for comparison: build the data matrix, one-hot encode it, cluster it."""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.spec import FeatureQuery


def materialise(query: FeatureQuery) -> DataFrame:
    """One row per joined row with the features' values, and w (1, or a pre-counted relation's counts)."""
    return _joined(query.validate(), False)


def counted(query: FeatureQuery) -> DataFrame:
    """The matrix as a bag: its different rows of features and w, how often each occurs.

    Each relation and each join is counted by the features and the keys that later joins still need, so a
    join that blows up moves different rows only. Joins are the same as in materialise, and so are the sums of w.
    """
    return _joined(query.validate(), True)


def _joined(q: FeatureQuery, bag: bool) -> DataFrame:
    def part(r):
        df = q.relations[r]
        w = [F.col("__w").alias(f"{r}__w")] if "__w" in df.columns else []
        out = df.select(*[F.col(k).alias(f"{r}__{k}") for k in q.keys(r)], *[f.column().alias(f.name) for f in q.of(r)], *w)
        return _bagged(out, out.columns[: len(out.columns) - len(w)], f"{r}__w") if bag else out

    df, done, edges = part(q.root), {q.root}, list(q.edges)
    while edges:
        e = next(x for x in edges if x.left in done or x.right in done)
        r = e.right if e.left in done else e.left
        on = [x for x in edges if r in (x.left, x.right) and (x.left in done or x.right in done)]
        if r not in done:
            cond = reduce(lambda a, b: a & b, [F.col(f"{x.left}__{a}") == F.col(f"{x.right}__{b}") for x in on for a, b in x.on])
            df = df.join(part(r), cond, "left" if e.how == "left" else "inner")
            if e.how == "left":
                df = df.withColumns({f.name: F.coalesce(f.name, F.lit(f.fallback())) for f in q.of(r)})
            done.add(r)
        edges = [x for x in edges if x not in on]
        if bag:
            ends = {f"{x.left}__{a}" for x in edges for a, _ in x.on} | {f"{x.right}__{b}" for x in edges for _, b in x.on}
            names = {f.name for f in q.features}
            df = _bagged(df, [c for c in df.columns if c in names or c in ends], "__w")
    ws = [c for c in df.columns if c.endswith("__w")]
    return df.select(*[f.name for f in q.features], _weight(ws).cast("bigint").alias("w"))


def _weight(ws: list[str]):
    return reduce(lambda a, b: a * b, [F.coalesce(c, F.lit(1)) for c in ws]) if ws else F.lit(1)


def _bagged(df: DataFrame, by: list[str], w: str) -> DataFrame:
    """df counted by some columns: their different rows and one weight."""
    ws = [c for c in df.columns if c.endswith("__w")]
    return df.groupBy(*by).agg(F.sum(_weight(ws).cast("bigint")).alias(w)).where(F.col(w).isNotNull())


def vectors(query: FeatureQuery, x: DataFrame):
    """x with a column of one-hot vectors, scaled by the features' weights; also the fitted pipeline."""
    from pyspark.ml import Pipeline
    from pyspark.ml.feature import ElementwiseProduct, OneHotEncoder, StringIndexerModel, VectorAssembler
    from pyspark.ml.linalg import Vectors

    cats, conts = ([f.name for f in query.features if f.kind == k] for k in ("cat", "cont"))
    stages, labels = [], _labels(x, cats)
    if cats:
        # A model a feature: one of several pads its features' labels to one length.
        stages += [StringIndexerModel.from_labels(ls, c, f"i_{c}") for c, ls in zip(cats, labels, strict=True)]
        stages.append(OneHotEncoder(inputCols=[f"i_{c}" for c in cats], outputCols=[f"v_{c}" for c in cats], dropLast=False))
    stages.append(VectorAssembler(inputCols=[*[f"v_{c}" for c in cats], *conts], outputCol="raw"))
    model = Pipeline(stages=stages).fit(x)
    sizes = [len(ls) for ls in labels]
    scale = np.concatenate([*[np.full(n, query.feature(c).scale) for c, n in zip(cats, sizes, strict=True)], *[[query.feature(c).scale] for c in conts]])
    return ElementwiseProduct(scalingVec=Vectors.dense(scale), inputCol="raw", outputCol="features").transform(model.transform(x)), model


def _labels(x: DataFrame, cats: list[str]) -> list[list[str]]:
    """Each feature's categories, those of the most joined rows first, then by name."""
    if not cats:
        return []
    each = F.explode(F.array(*[F.struct(F.lit(i).alias("i"), F.col(c).alias("v")) for i, c in enumerate(cats)]))
    out: list[list[str]] = [[] for _ in cats]
    for r in x.select(each.alias("e"), "w").groupBy("e.i", "e.v").agg(F.sum("w").alias("w")).orderBy("i", F.desc("w"), "v").collect():
        out[r["i"]].append(r["v"])
    return out


def standard_kmeans(query: FeatureQuery, k: int, seed: int = 1, max_iter: int = 20, build: Callable[[FeatureQuery], DataFrame] = materialise) -> tuple[float, dict[str, float]]:
    """Objective of k-means on the one-hot matrix, and the seconds for building and clustering it.

    build=counted clusters the same matrix as a bag: points of weight w stand for w equal rows, and the
    seconds are those of the bag.
    """
    from pyspark.ml.clustering import KMeans

    t0 = time.perf_counter()
    x = build(query).persist()
    x.count()
    t1 = time.perf_counter()
    v, _ = vectors(query, x)
    model = KMeans(k=k, seed=seed, maxIter=max_iter, weightCol="w", featuresCol="features").fit(v.select("features", F.col("w").cast("double").alias("w")))
    cost = float(model.summary.trainingCost)
    t2 = time.perf_counter()
    x.unpersist()
    return cost, {"materialise": t1 - t0, "cluster": t2 - t1}


def dense_lloyd(x: np.ndarray, w: np.ndarray, seeds: np.ndarray, max_iter: int = 20, tol: float = 1e-4) -> tuple[np.ndarray, float]:
    """Weighted Lloyd on explicit vectors, from given seeds; ties to the smallest id, empty clusters stay."""
    c, last = seeds.astype(float).copy(), np.inf
    for _ in range(max_iter):
        d = (x * x).sum(1)[:, None] - 2 * x @ c.T + (c * c).sum(1)
        a = d.argmin(1)
        cost = float((w * np.maximum(d[np.arange(len(x)), a], 0)).sum())
        mass = np.bincount(a, weights=w, minlength=len(c))
        sums = np.stack([np.bincount(a, weights=w * x[:, j], minlength=len(c)) for j in range(x.shape[1])], 1)
        c = np.where(mass[:, None] > 0, sums / np.maximum(mass, 1e-300)[:, None], c)
        if last - cost <= tol * max(abs(last), 1e-300) and np.isfinite(last):
            break
        last = cost
    d = (x * x).sum(1)[:, None] - 2 * x @ c.T + (c * c).sum(1)
    return c, float((w * np.maximum(d.min(1), 0)).sum())


def drawn(x: DataFrame, fraction: float, seed: int = 1) -> DataFrame:
    """A sample of a bag's rows, each drawn with probability fraction: of w equal ones a binomial number stays.

    Seed and values decide the draw, so it is the same on any partitioning.
    """
    names = [c for c in x.columns if c != "w"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            keys, ws = b.column("__key").to_numpy().view(np.uint64), b.column("w").to_numpy()
            w = [np.random.Generator(np.random.Philox(key=int(h))).binomial(n, fraction) for h, n in zip(keys, ws, strict=True)]
            yield pa.RecordBatch.from_arrays([*[b.column(c) for c in names], pa.array(w, pa.int64())], [*names, "w"])

    keyed = x.select(*names, "w", F.xxhash64(F.lit(seed), *names).alias("__key"))
    return keyed.mapInArrow(run, x.select(*names, F.col("w").cast("bigint").alias("w")).schema).where("w > 0")


def sample_kmeans(query: FeatureQuery, k: int, fraction: float, seed: int = 1) -> DataFrame:
    """The alternative of sampling the matrix: centers of k-means on a sample of joined rows."""
    from pyspark.ml.clustering import KMeans

    x = drawn(counted(query), fraction, seed).persist()
    v, _ = vectors(query, x)
    model = KMeans(k=k, seed=seed, weightCol="w").fit(v.select("features", F.col("w").cast("double").alias("w")))
    x.unpersist()
    return query.relations[query.root].sparkSession.createDataFrame([(i, [float(z) for z in c]) for i, c in enumerate(model.clusterCenters())], "cluster int, center array<double>")


def time_export(df: DataFrame, path: str, fmt: str = "csv") -> float:
    """Seconds to write the matrix where a separate clustering library would read it; 'noop' writes nowhere."""
    t = time.perf_counter()
    w = df.write.format(fmt).mode("overwrite")
    w.save() if fmt == "noop" else w.save(path)
    return time.perf_counter() - t
