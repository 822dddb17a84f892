"""A hidden Markov language model whose Baum-Welch counts are aggregated across partitions.

Tokens are emitted in two steps: a state emits a word class, the class emits the word. The most
frequent words are classes of their own; all other words, known or not, fall into a fixed number of
classes by their last bytes, and within a class a word has the share (count + 1) / (tokens + types
+ 1), the spare 1 standing for every unknown word. State parameters are therefore of bounded size,
while word counts grow with the corpus: the most frequent are held by every task, the others are
joined. The scaled forward recursion gives the exact likelihood of a text.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common as c

STATES, CLASSES, TAILS = 10, 4096, 1024
#: Word counts that every task holds; rarer words are joined.
HELD = 1 << 18
#: Rows that the first parameters are drawn from; the passes after it read all training rows.
FIRST_ROWS, FIRST_MIXING, FIRST_PASSES, PASSES = 500, 12, 4, 2
_LOW = np.uint64(TAILS - 1)
#: The key of the end token, of the last tail class (a fixed value; no word has it but by a chance of 2^-54).
END = np.uint64(0xE5D1A7C3B9F0_0000 | (TAILS - 1))


def token_keys(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Keys of all tokens of a column of texts, text after text, each closed by its end; and how many each text has.

    A key is 54 bits of the word's hash, then 10 bits of its class, which its last three bytes decide.
    """
    h, tail, first, last = c.word_hashes(texts)
    low = c.mixed(tail.astype(np.uint64), 60) & _LOW
    many = last - first + 1
    out = np.full(len(h) + len(many), END, np.uint64)
    place = np.ones(len(out), bool)
    place[np.cumsum(many) - 1] = False
    out[place] = (h & ~_LOW) | low
    return out, many


def word_counts(documents: DataFrame) -> DataFrame:
    """key, n over all training rows: each task counts its own, then they are summed."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[np.ndarray] = []
        total = 0
        for b in batches:
            b = b.filter(pc.invert(b.column("held_out")))
            for at in range(0, b.num_rows, 2000):
                held.append(token_keys(b.column("text").slice(at, 2000))[0])
                total += len(held[-1])
                if total > 3_000_000:
                    yield _counted(held)
                    held, total = [], 0
        if held:
            yield _counted(held)

    return documents.select("text", "held_out").mapInArrow(run, "key long, n long").groupBy("key").agg(F.sum("n").alias("n"))


def _counted(held: list[np.ndarray]) -> pa.RecordBatch:
    k, n = np.unique(np.concatenate(held), return_counts=True)
    return pa.RecordBatch.from_arrays([pa.array(k.view(np.int64)), pa.array(n, pa.int64())], ["key", "n"])


class Vocabulary:
    """What every task holds: frequent keys (sorted) with counts and classes, and the tail classes' totals."""

    def __init__(self, counts: DataFrame):
        self.tokens, self.types = (int(x or 0) for x in counts.agg(F.sum("n"), F.count("*")).first())
        top = counts.where(F.col("n") >= self.least_count(counts)).toArrow()  # at most HELD rows
        keys, n = top.column("key").to_numpy().view(np.uint64), top.column("n").to_numpy()
        own = np.full(len(keys), -1)
        rank = np.lexsort((keys.view(np.int64), -n))
        own[rank[:CLASSES]] = np.arange(min(CLASSES, len(keys)))
        sums = counts.groupBy(F.col("key").bitwiseAND(TAILS - 1).alias("tail")).agg(F.sum("n").alias("n"), F.count("*").alias("v")).collect()
        spread = np.ones(TAILS)
        for r in sums:
            spread[r["tail"]] += r["n"] + r["v"]
        mine = keys[own >= 0]
        np.subtract.at(spread, (mine & _LOW).astype(np.int64), n[own >= 0] + 1.0)
        order = np.argsort(keys)
        self.keys, self.n, self.own = keys[order], n[order], own[order].astype(np.int32)
        self.log_spread = np.log10(spread)

    @staticmethod
    def least_count(counts: DataFrame) -> int:
        """The least power of 2^(1/16) such that at most HELD keys are counted so often: from a count by powers, so nothing is sorted or gathered."""
        steps = F.floor(F.log2(F.col("n").cast("double")) * 16 + 1e-9).cast("int")
        total, least = 0, None
        for r in sorted(counts.groupBy(steps.alias("step")).agg(F.count("*").alias("keys"), F.min("n").alias("least")).collect(), reverse=True):  # at most 16 * 63 rows
            total += r["keys"]
            if total > HELD:
                break
            least = r["least"]
        return least if least is not None else (1 << 62)

    @property
    def classes(self) -> int:
        return CLASSES + TAILS

    def find(self, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Whether each key is held, and where."""
        if not len(self.keys):
            return np.zeros(len(keys), bool), np.zeros(len(keys), np.int64)
        at = np.minimum(np.searchsorted(self.keys, keys), len(self.keys) - 1)
        return self.keys[at] == keys, at


def encoded(documents: DataFrame, vocabulary: Vocabulary) -> DataFrame:
    """Of every row: its class sequence, the parts of its scores that need no join, and its rarer keys."""
    spark = documents.sparkSession
    shared = spark.sparkContext.broadcast(vocabulary)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        v = shared.value
        for batch in batches:
            for lo in range(0, batch.num_rows, 1000):
                b = batch.slice(lo, 1000)
                k, many = token_keys(b.column("text"))
                ends = np.cumsum(many)
                starts = ends - many
                held, at = v.find(k)
                logs = np.where(held, np.log10(v.n[at] + 1.0) if len(v.n) else 0.0, 0.0)
                own = np.where(held, v.own[at] if len(v.own) else -1, -1)
                tail = own < 0
                low = (k & _LOW).astype(np.int64)
                classes = np.where(tail, CLASSES + low, own).astype("<u2")
                total = lambda x: np.add.reduceat(x, starts) if len(starts) else np.empty(0)
                rare = [np.unique(k[i:j][~held[i:j]], return_counts=True) for i, j in zip(starts, ends, strict=True)]
                stops = pa.array(np.cumsum([0, *(len(x) for x, _ in rare)], dtype=np.int32))
                flat = [np.concatenate([x[i] for x in rare]) if rare else np.empty(0, np.uint64) for i in (0, 1)]
                yield pa.RecordBatch.from_arrays(
                    [
                        *(b.column(x) for x in ("doc_id", "row", "held_out")), pa.array([classes[i:j].tobytes() for i, j in zip(starts, ends, strict=True)], pa.binary()),
                        pa.array(many, pa.int64()), pa.array(total(held.astype(np.int64)), pa.int64()), pa.array(total(logs), pa.float64()),
                        pa.array(total(np.where(tail, logs, 0.0)), pa.float64()), pa.array(total(np.where(tail, v.log_spread[low], 0.0)), pa.float64()),
                        pa.ListArray.from_arrays(stops, pa.array(flat[0].view(np.int64))), pa.ListArray.from_arrays(stops, pa.array(flat[1], pa.int32())),
                    ],
                    ["doc_id", "row", "held_out", "classes", "n_tokens", "n_held", "log_held", "log_tail", "log_spread", "rare", "many"],
                )

    return documents.mapInArrow(run, "doc_id long, row long, held_out boolean, classes binary, n_tokens long, n_held long, log_held double, log_tail double, log_spread double, rare array<long>, many array<int>")


# ---- the chain --------------------------------------------------------------------------------


#: Tokens of the texts that are walked together; a longer text is walked alone, in stretches of as many.
STRETCH = 1 << 17


def _packed(seqs: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """Sequences of falling length, as one array by time; at time t the first width[t] sequences run."""
    time = np.concatenate([np.arange(len(s), dtype=np.int32) for s in seqs])
    return np.concatenate(seqs).astype(np.int64)[np.argsort(time, kind="stable")], np.bincount(time)


def forward(x: np.ndarray, width: np.ndarray, start: np.ndarray, move: np.ndarray, emit_t: np.ndarray, before: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Scaled forward variables and scales, by time; before holds the variables of the stretch before, if any."""
    alpha, scale = emit_t[x], np.empty(len(x))
    at = 0
    for n in width:
        a = alpha[at : at + n]
        a *= start if before is None else before[:n] @ move
        s = a.sum(1)
        a /= s[:, None]
        scale[at : at + n] = s
        before, at = a, at + n
    return alpha, scale


def expected(x: np.ndarray, width: np.ndarray, start: np.ndarray, move: np.ndarray, emit_t: np.ndarray, before: np.ndarray | None = None, after: np.ndarray | None = None) -> tuple[tuple[np.ndarray, np.ndarray, np.ndarray], np.ndarray]:
    """Baum-Welch counts (starts, moves, emissions by class), and what a stretch before this one needs of it.

    before holds the forward variables of the stretch before, after what the stretch after has given.
    """
    alpha, scale = forward(x, width, start, move, emit_t, before)
    ends = np.cumsum(width)
    moves = np.zeros_like(move)
    beta = np.ones_like(alpha)
    if after is not None:
        moves += alpha[-1:].T @ after
        beta[-1:] = after @ move.T
    for t in range(len(width) - 2, -1, -1):
        n, lo, hi = width[t + 1], ends[t] - width[t], ends[t]
        nxt = slice(hi, hi + n)
        w = emit_t[x[nxt]] * beta[nxt] / scale[nxt, None]
        moves += alpha[lo : lo + n].T @ w
        beta[lo : lo + n] = w @ move.T
    gamma = alpha * beta
    gamma /= gamma.sum(1, keepdims=True)
    emits = np.array([np.bincount(x, weights=g, minlength=len(emit_t)) for g in gamma.T])
    starts = gamma[: width[0]].sum(0) if before is None else np.zeros(len(move))
    return (starts, moves * move, emits), emit_t[x[: width[0]]] * beta[: width[0]] / scale[: width[0], None]


def _stretches(seq: np.ndarray) -> list[np.ndarray]:
    return [seq[i : i + STRETCH].astype(np.int64) for i in range(0, len(seq), STRETCH)]


def all_counts(seqs: list[np.ndarray], start: np.ndarray, move: np.ndarray, emit_t: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """Baum-Welch counts of sequences, part by part; a long one keeps only the variables between its stretches."""
    for seq in (s for s in seqs if len(s) > STRETCH):
        parts, befores = _stretches(seq), [None]
        for x in parts[:-1]:
            befores.append(forward(x, np.ones(len(x), np.int64), start, move, emit_t, befores[-1])[0][-1:].copy())
        after = None
        for x, before in zip(parts[::-1], befores[::-1], strict=True):
            got, after = expected(x, np.ones(len(x), np.int64), start, move, emit_t, before, after)
            yield got
    for _, x, width in _groups(seqs):
        yield expected(x, width, start, move, emit_t)[0]


def log_likelihoods(seqs: list[np.ndarray], start: np.ndarray, move: np.ndarray, emit_t: np.ndarray) -> np.ndarray:
    """log10 of every sequence's probability by the chain."""
    out = np.zeros(len(seqs))
    for i, seq in enumerate(seqs):
        if len(seq) > STRETCH:
            before = None
            for x in _stretches(seq):
                alpha, scale = forward(x, np.ones(len(x), np.int64), start, move, emit_t, before)
                before = alpha[-1:].copy()
                out[i] += np.log10(scale).sum()
    for part, x, width in _groups(seqs):
        _, scale = forward(x, width, start, move, emit_t)
        place = np.concatenate([np.arange(n) for n in width])
        out[part] = np.bincount(place, weights=np.log10(scale), minlength=len(part))
    return out


def _groups(seqs: list[np.ndarray], many: int = 256) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """Places and packed sequences of those of at most STRETCH tokens, so many at once that they have at most twice as many tokens."""
    order = np.array([i for i in np.argsort([-len(s) for s in seqs], kind="stable") if len(seqs[i]) <= STRETCH], dtype=np.int64)
    at = 0
    while at < len(order):
        total = np.cumsum([len(seqs[i]) for i in order[at : at + many]])
        n = max(1, int(np.searchsorted(total, 2 * STRETCH, "right")))
        part = order[at : at + n]
        yield part, *_packed([seqs[j] for j in part])
        at += n


def renewed(counts: tuple[np.ndarray, np.ndarray, np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Parameters from counts; every state keeps a little of the common emissions, so no text has likelihood 0."""
    s, m, e = counts
    common = e.sum(0) + 0.5
    e = e + 50 * common / common.sum()
    m = m + 0.1
    s = s + 0.1
    return s / s.sum(), m / m.sum(1, keepdims=True), e / e.sum(1, keepdims=True)


def first_parameters(seqs: list[np.ndarray], classes: int, states: int = STATES) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Parameters from a few texts: a mixture over whole texts names the states, then some passes of Baum-Welch."""
    rng = np.random.default_rng(7)
    n = np.array([np.bincount(s, minlength=classes) for s in seqs], dtype=float) if seqs else np.zeros((1, classes))
    common = n.sum(0) + 0.5
    common /= common.sum()
    share = rng.dirichlet(np.full(states, 0.3), len(n))
    for _ in range(FIRST_MIXING):
        e = share.T @ n + 20 * common
        e /= e.sum(1, keepdims=True)
        logs = n @ np.log(e).T + np.log(share.mean(0) + 1e-9)
        share = np.exp((logs - logs.max(1, keepdims=True)) / 4)
        share /= share.sum(1, keepdims=True)
    move = np.full((states, states), 0.03 / states) + 0.97 * np.eye(states)
    now = share.mean(0) + 1e-3, move, e
    now = now[0] / now[0].sum(), move, e
    for _ in range(FIRST_PASSES if seqs else 0):
        sums = [np.zeros(states), np.zeros((states, states)), np.zeros((states, classes))]
        for counts in all_counts(seqs, now[0], now[1], np.ascontiguousarray(now[2].T)):
            for total, got in zip(sums, counts, strict=True):
                total += got
        now = renewed(tuple(sums))
    return now


def one_pass(read: DataFrame, now: tuple[np.ndarray, np.ndarray, np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """One Baum-Welch pass over all training rows: tasks add up their own counts, Spark adds up the tasks'."""
    states, classes = now[2].shape
    shared = read.sparkSession.sparkContext.broadcast(now)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        start, move, emit = shared.value
        emit_t = np.ascontiguousarray(emit.T)
        sums = np.zeros(states), np.zeros((states, states)), np.zeros((states, classes))
        for b in batches:
            for counts in all_counts([np.frombuffer(y.as_buffer(), "<u2") for y in b.column("classes")], start, move, emit_t):
                for total, got in zip(sums, counts, strict=True):
                    total += got
        flat = np.concatenate([s.ravel() for s in sums])
        i = np.flatnonzero(flat)
        yield pa.RecordBatch.from_arrays([pa.array(i.astype(np.int32)), pa.array(flat[i])], ["i", "v"])

    got = read.where("not held_out").select("classes").mapInArrow(run, "i int, v double").groupBy("i").agg(F.sum("v").alias("v")).toArrow()  # at most states * (1 + states + classes) rows
    flat = np.zeros(states * (1 + states + classes))
    flat[got.column("i").to_numpy()] = got.column("v").to_numpy()
    a, b = states, states + states * states
    return renewed((flat[:a], flat[a:b].reshape(states, states), flat[b:].reshape(states, classes)))


def score(documents: DataFrame) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score for every row of documents.

    Rows whose crc32(doc_id as text) mod 7 is 2 are held out. A null or empty text is its end token
    alone. Rows that repeat are scored each for itself and counted each. An empty table gives an
    empty result.
    """
    docs = documents.select("doc_id", F.xxhash64("doc_id", F.coalesce("text", F.lit(""))).alias("row"), F.coalesce(c.remainder(F.col("doc_id"), 7) == 2, F.lit(False)).alias("held_out"), "text").select("doc_id", "row", "held_out", "text")
    counts = c.written(word_counts(docs))
    vocabulary = Vocabulary(counts)
    read = c.written(encoded(docs, vocabulary))

    some = read.where("not held_out").orderBy(F.xxhash64("row"), "row").select("classes").limit(FIRST_ROWS).collect()
    now = first_parameters([np.frombuffer(r["classes"], "<u2") for r in some], vocabulary.classes)
    for _ in range(PASSES):
        now = one_pass(read, now)
    shared = read.sparkSession.sparkContext.broadcast((now[0], now[1], np.ascontiguousarray(now[2].T)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        start, move, emit_t = shared.value
        for b in batches:
            out = log_likelihoods([np.frombuffer(y.as_buffer(), "<u2") for y in b.column("classes")], start, move, emit_t)
            keep = [k for k in b.schema.names if k != "classes"]
            yield pa.RecordBatch.from_arrays([*(b.column(k) for k in keep), pa.array(out)], [*keep, "log_chain"])

    kept = "doc_id long, row long, held_out boolean, n_tokens long, n_held long, log_held double, log_tail double, log_spread double"
    chained = read.drop("rare", "many").mapInArrow(lambda it: run(b.select([*[x.split()[0] for x in kept.split(", ")], "classes"]) for b in it), f"{kept}, log_chain double")
    rare = read.select("row", F.explode(F.arrays_zip(F.col("rare").alias("key"), "many")).alias("x")).select("row", "x.key", "x.many")
    joined = rare.join(counts, "key").select("row", F.col("many").cast("long").alias("known"), (F.col("many") * F.log10(F.col("n") + 1.0)).alias("logs"))
    copies = read.groupBy("row").agg(F.count("*").alias("copies"))
    sums = joined.groupBy("row").agg(F.sum("known").alias("known"), F.sum("logs").alias("logs")).join(copies, "row").select("row", (F.expr("known div copies")).alias("known"), (F.col("logs") / F.col("copies")).alias("logs"))
    size = float(np.log10(vocabulary.tokens + vocabulary.types + 1))
    logs = F.coalesce("logs", F.lit(0.0))
    return chained.join(sums, "row", "left").select(
        "doc_id", "held_out", "n_tokens", (F.col("n_held") + F.coalesce("known", F.lit(0).cast("long"))).alias("n_known"), F.lit(vocabulary.tokens).cast("long").alias("train_tokens"),
        (F.col("log_held") + logs - F.col("n_tokens") * size).alias("base_score"), (F.col("log_chain") + F.col("log_tail") + logs - F.col("log_spread")).alias("score"),
    )
