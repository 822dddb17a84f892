"""Toxicity by the nearest labelled examples: exact TF-IDF cosine over a block-max inverted index.

Terms are words and short word starts; a lexicon of at most LEXICON terms is chosen on a bounded
sample of labelled rows by the chi-square of term and label. Document frequencies count every
document. The labelled sample is indexed in blocks of examples with the greatest weight of each
term in each block; a query scores a block only if its bound can still enter the top k, so the
neighbours are exact. Similarity-weighted votes are calibrated by isotonic regression on
leave-one-out votes of the sample.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass
from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import common as c

#: Labelled rows of either label that the classifier is fitted on (those of the smallest id hash).
SAMPLE = 3000
#: Terms at most; rows a term needs; its chi-square; and how many times likelier it must be under one label.
LEXICON, LEAST_DF, LEAST_CHI2, LEAST_LIFT = 512, 8, 20.0, 3.0
STARTS = (4, 5, 6)
NEIGHBOURS, BLOCK, LIMIT = 16, 64, 0.7
#: Weight of the prior in a vote, in units of similarity.
PRIOR = 0.25
_WORD = re.compile(r"[^\W_]+")


def terms(word: str) -> list[str]:
    return [word, *(f"{word[:n]}*" for n in STARTS if len(word) > n)]


class Terms:
    """Term counts of a text over a lexicon, with a bounded memory of words."""

    def __init__(self, lexicon: dict[str, int]):
        self.lexicon, self.known = lexicon, {}

    def __call__(self, text: str | None) -> dict[int, int]:
        out: dict[int, int] = {}
        if len(self.known) > 200_000:
            self.known.clear()
        for w, n in Counter(_WORD.findall((text or "").lower())).items():
            ids = self.known.get(w)
            if ids is None:
                ids = self.known[w] = tuple(self.lexicon[t] for t in terms(w) if t in self.lexicon)
            for i in ids:
                out[i] = out.get(i, 0) + n
        return out


def choose_lexicon(sample: DataFrame, most: int = LEXICON) -> list[str]:
    """The terms of sample (text, label) that say most about the label, best first."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen = (Counter(), Counter())
        rows = [0, 0]
        for b in batches:
            for t, y in zip(b.column("text").to_pylist(), b.column("label").to_pylist(), strict=True):
                seen[y].update({x for w in set(_WORD.findall((t or "").lower())) for x in terms(w)})
                rows[y] += 1
        keys = list(seen[0] | seen[1])
        yield pa.RecordBatch.from_arrays([pa.array(["", *keys]), *[pa.array([rows[y], *(seen[y][k] for k in keys)], pa.int64()) for y in (0, 1)]], ["term", "clean", "toxic"])

    sums = c.written(sample.select("text", "label").mapInArrow(count, "term string, clean long, toxic long").groupBy("term").agg(F.sum("clean").alias("a"), F.sum("toxic").alias("b")).where(f"a + b >= {LEAST_DF} or term = ''"))
    total = sums.where("term = ''").first()
    if total is None or not total["a"] or not total["b"]:
        return []
    n0, n1 = float(total["a"]), float(total["b"])
    cross = F.col("b") * (n0 - F.col("a")) - F.col("a") * (n1 - F.col("b"))
    chi2 = cross * cross * (n0 + n1) / ((F.col("a") + F.col("b")) * (n0 + n1 - F.col("a") - F.col("b") + 1e-9) * n0 * n1)
    rows = sums.where("term != ''").withColumn("chi2", chi2).where((F.col("chi2") >= LEAST_CHI2) & ((F.col("b") * n0 >= F.col("a") * n1 * LEAST_LIFT) | (F.col("b") * n0 * LEAST_LIFT <= F.col("a") * n1))).orderBy(F.desc("chi2"), "term").limit(most).collect()
    return [r["term"] for r in rows]


@dataclass
class BlockMaxIndex:
    """Unit vectors of examples in blocks; bound[t, b] is the greatest weight of term t in block b."""

    ids: np.ndarray
    labels: np.ndarray
    rows: np.ndarray
    bound: np.ndarray

    @classmethod
    def of(cls, ids: np.ndarray, labels: np.ndarray, rows: np.ndarray) -> BlockMaxIndex:
        order = np.lexsort((ids, rows.argmax(1))) if len(ids) else np.empty(0, np.int64)
        ids, labels, rows = ids[order], labels[order], rows[order]
        blocks = [rows[i : i + BLOCK].max(0) for i in range(0, len(rows), BLOCK)]
        return cls(ids, labels, rows, np.array(blocks).T if blocks else np.zeros((rows.shape[1], 0)))

    def search(self, queries: np.ndarray, k: int, skip: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
        """Places of the k most similar examples of each query (-1: none) and their similarities; ties go to the smaller id.

        skip[q] is the place of an example that query q must not see (leave-one-out).
        """
        n = len(queries)
        at, sim = np.full((n, k), -1, np.int64), np.zeros((n, k))
        if not n or not len(self.ids):
            return at, sim
        bounds = queries @ self.bound
        order = np.argsort(-bounds.max(0), kind="stable")
        for b in order:
            q = np.flatnonzero((bounds[:, b] > 1e-9) & (bounds[:, b] + 1e-9 >= sim[:, -1]))
            if not len(q):
                continue
            lo = b * BLOCK
            got = np.round(queries[q] @ self.rows[lo : lo + BLOCK].T, 9)
            places = np.broadcast_to(np.arange(lo, lo + got.shape[1]), got.shape)
            if skip is not None:
                got = np.where(places == skip[q, None], 0, got)
            alls, allp = np.hstack([sim[q], got]), np.hstack([at[q], places])
            allp = np.where(alls > 0, allp, -1)
            tie = np.where(allp >= 0, self.ids[allp], np.iinfo(np.int64).max)
            best = np.lexsort((tie, -alls), axis=1)[:, :k]
            sim[q], at[q] = np.take_along_axis(alls, best, 1), np.take_along_axis(allp, best, 1)
        return at, sim


def isotonic(x: np.ndarray, y: np.ndarray, w: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Knots of the weighted non-decreasing fit of y on x (pool adjacent violators)."""
    order = np.argsort(x, kind="stable")
    pools: list[list[float]] = []
    for xi, yi, wi in zip(x[order], y[order], w[order], strict=True):
        pools.append([xi * wi, yi * wi, wi])
        while len(pools) > 1 and pools[-2][1] * pools[-1][2] >= pools[-1][1] * pools[-2][2]:
            last = pools.pop()
            pools[-1] = [a + b for a, b in zip(pools[-1], last, strict=True)]
    return np.array([p[0] / p[2] for p in pools]), np.array([p[1] / p[2] for p in pools])


@dataclass
class Model:
    lexicon: list[str]
    idf: np.ndarray
    index: BlockMaxIndex
    weights: np.ndarray  # of the two labels, so that the sample stands for all labelled rows
    prior: float
    empty: float
    knots: tuple[np.ndarray, np.ndarray]

    @cached_property
    def places(self) -> dict[int, int]:
        return {int(d): i for i, d in enumerate(self.index.ids)}

    def vectors(self, ids: list[list[int]], counts: list[list[int]]) -> np.ndarray:
        return vectors(ids, counts, self.idf)

    def votes(self, at: np.ndarray, sim: np.ndarray) -> np.ndarray:
        y = np.where(at >= 0, self.index.labels[at], 0) if len(self.index.labels) else np.zeros_like(sim)
        w = sim * self.weights[y.astype(int)]
        return ((w * y).sum(1) + PRIOR * self.prior) / (w.sum(1) + PRIOR)

    def scores(self, q: np.ndarray, doc_ids: list[int | None]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Scores, places and similarities; an example of the index does not see itself, so its own label has no part in its score."""
        at, sim = self.index.search(q, NEIGHBOURS, skip=np.array([self.places.get(d, -1) for d in doc_ids], dtype=np.int64))
        vote = self.votes(at, sim)
        fitted = np.interp(vote, *self.knots) if len(self.knots[0]) else vote
        return np.where(sim[:, 0] > 0, 0.98 * fitted + 0.02 * vote, self.empty), at, sim


def vectors(ids: list[list[int]], counts: list[list[int]], idf: np.ndarray) -> np.ndarray:
    out = np.zeros((len(ids), len(idf)))
    for i, (a, n) in enumerate(zip(ids, counts, strict=True)):
        if a:
            out[i, a] = (1 + np.log(n)) * idf[a]
    norm = np.linalg.norm(out, axis=1, keepdims=True)
    return np.divide(out, norm, out=out, where=norm > 0)


def counted(documents: DataFrame, lexicon: list[str]) -> DataFrame:
    """doc_id, ids, counts: the lexicon terms of every row of documents."""
    index = {t: i for i, t in enumerate(lexicon)}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        count = Terms(index)
        for batch in batches:
            for at in range(0, batch.num_rows, 2000):
                b = batch.slice(at, 2000)
                got = [count(t) for t in b.column("text").to_pylist()]
                yield pa.RecordBatch.from_arrays([b.column("doc_id").cast(pa.int64()), pa.array([list(g) for g in got], pa.list_(pa.int32())), pa.array([list(g.values()) for g in got], pa.list_(pa.int32()))], ["doc_id", "ids", "counts"])

    return documents.select("doc_id", "text").mapInArrow(run, "doc_id long, ids array<int>, counts array<int>")


def held_out(doc_id: Column) -> Column:
    return F.coalesce(c.remainder(doc_id, 3) == 1, F.lit(False))


def training_sample(documents: DataFrame, labels: DataFrame, most: int = SAMPLE) -> tuple[DataFrame, dict[int, int]]:
    """doc_id, label, text of at most `most` rows of either label, those of the smallest id hash, and the labels' full counts; held-out rows are out."""
    known = c.written(labels.where("toxic in (0, 1)").select("doc_id", F.col("toxic").cast("int").alias("label")).where(~held_out(F.col("doc_id"))).dropDuplicates(["doc_id"]).join(documents.select("doc_id").distinct(), "doc_id", "left_semi"))
    some = [known.where(F.col("label") == y).orderBy(F.xxhash64("doc_id"), "doc_id").limit(most) for y in (0, 1)]
    picked = c.written(some[0].unionByName(some[1]))
    counts = {r["label"]: r["count"] for r in known.groupBy("label").count().collect()}
    rows = documents.select("doc_id", "text").join(F.broadcast(picked), "doc_id").dropDuplicates(["doc_id"])
    return c.written(rows), counts


def _document_counts(read: DataFrame, size: int) -> DataFrame:
    """i, n: in how many rows each lexicon term stands; tasks count their own rows first."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(size, np.int64)
        for b in batches:
            total += np.bincount(b.column("ids").flatten().to_numpy(zero_copy_only=False), minlength=size)[:size] if size else 0
        i = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(i.astype(np.int32)), pa.array(total[i])], ["i", "n"])

    return read.select("ids").mapInArrow(run, "i int, n long").groupBy("i").agg(F.sum("n").alias("n"))


def fit(documents: DataFrame, labels: DataFrame, most: int = SAMPLE) -> tuple[Model, DataFrame]:
    """The model, and the lexicon terms of every document."""
    sample, counts = training_sample(documents, labels, most)
    lexicon = choose_lexicon(sample.dropDuplicates(["text"]))
    read = c.written(counted(documents, lexicon))
    n, df = read.count(), np.zeros(len(lexicon))
    for r in _document_counts(read, len(lexicon)).collect():  # at most LEXICON rows
        df[r["i"]] = r["n"]
    idf = np.log((n + 1) / (df + 1)) + 1e-3
    rows = read.join(F.broadcast(sample.select("doc_id", "label")), "doc_id").dropDuplicates(["doc_id"]).orderBy("doc_id").collect()  # at most 2 * most short rows
    y = np.array([r["label"] for r in rows], dtype=np.int64)
    x = vectors([r["ids"] for r in rows], [r["counts"] for r in rows], idf)
    seen = np.bincount(y, minlength=2)
    weights = np.array([counts.get(k, 0) / seen[k] if seen[k] else 0.0 for k in (0, 1)])
    weights = weights / max(weights.max(), 1e-12)
    total = (weights * seen).sum()
    prior = float(weights[1] * seen[1] / total) if total else 0.0
    full = x.any(1)
    bare = np.bincount(y[~full], minlength=2) * weights
    empty = float((bare[1] + prior) / (bare.sum() + 1)) if total else 0.0
    index = BlockMaxIndex.of(np.array([r["doc_id"] for r in rows], dtype=np.int64)[full], y[full], x[full])
    model = Model(lexicon, idf, index, weights, prior, empty, (np.empty(0), np.empty(0)))
    votes = []
    for i in range(0, len(index.ids), 1000):
        part = np.arange(i, min(i + 1000, len(index.ids)))
        at, sim = index.search(index.rows[part], NEIGHBOURS, skip=part)
        votes.append(model.votes(at, sim))
    if votes:
        model.knots = isotonic(np.concatenate(votes), index.labels.astype(float), weights[index.labels])
    return model, read


def score(documents: DataFrame, labels: DataFrame, most: int = SAMPLE) -> DataFrame:
    """doc_id, held_out, score, predicted, evidence for every row of documents.

    evidence holds the labelled neighbours (doc_id, label, similarity). A null or empty text, and
    any text without a lexicon term, scores the share of toxic rows among such examples and has no
    evidence. Without labels of both kinds no term is chosen and every score is that share.
    Rows that repeat are scored each for itself.
    """
    model, read = fit(documents.select("doc_id", "text"), labels, most)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kind = pa.list_(pa.struct([("doc_id", pa.int64()), ("label", pa.int32()), ("similarity", pa.float64())]))
        for batch in batches:
            for lo in range(0, batch.num_rows, 1000):
                b = batch.slice(lo, 1000)
                ids, counts = b.column("ids").to_pylist(), b.column("counts").to_pylist()
                some = np.array([i for i, x in enumerate(ids) if x], dtype=np.int64)
                s = np.full(b.num_rows, model.empty)
                evidence: list[list[dict]] = [[] for _ in ids]
                if len(some):
                    s[some], at, sim = model.scores(model.vectors([ids[i] for i in some], [counts[i] for i in some]), b.column("doc_id").take(pa.array(some)).to_pylist())
                    for i, a, v in zip(some, at, sim, strict=True):
                        evidence[i] = [{"doc_id": int(model.index.ids[p]), "label": int(model.index.labels[p]), "similarity": float(z)} for p, z in zip(a, v, strict=True) if p >= 0]
                s = np.clip(s, 0.0, 1.0)
                yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(s), pa.array((s >= LIMIT).astype(np.int32)), pa.array(evidence, kind)], ["doc_id", "score", "predicted", "evidence"])

    out = read.mapInArrow(run, "doc_id long, score double, predicted int, evidence array<struct<doc_id: long, label: int, similarity: double>>")
    return out.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", "predicted", "evidence")


def keep_clean(documents: DataFrame, labels: DataFrame, most: int = SAMPLE) -> DataFrame:
    """The rows of documents, all columns, that score calls clean; one more pass over the texts, no shuffle.

    Every row is judged for itself, so rows that repeat go or stay together, and null ids are ids like
    any other. Null and empty texts are judged as score does. An empty table gives an empty result.
    """
    model, _ = fit(documents.select("doc_id", "text"), labels, most)
    index = {t: i for i, t in enumerate(model.lexicon)}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        count = Terms(index)
        for batch in batches:
            for lo in range(0, batch.num_rows, 1000):
                b = batch.slice(lo, 1000)
                got = [count(t) for t in b.column("text").to_pylist()]
                some = np.array([i for i, g in enumerate(got) if g], dtype=np.int64)
                keep = np.full(b.num_rows, model.empty < LIMIT)
                if len(some):
                    keep[some] = model.scores(model.vectors([list(got[i]) for i in some], [list(got[i].values()) for i in some]), b.column("doc_id").take(pa.array(some)).to_pylist())[0] < LIMIT
                yield b.filter(pa.array(keep))

    return documents.mapInArrow(run, documents.schema)
