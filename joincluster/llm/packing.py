"""Packing token pieces into sequences by a configuration linear program over the length histogram.

A configuration is a multiset of lengths that fits one sequence. The program (fewest sequences that
hold every piece) is solved by multiplicative weights: each length has a price, its share of a
sequence times a weight that falls as its demand is served and is greatest for what lags behind; a
knapsack dynamic program, bounded by what is left of each length, prices the best configuration, and
as much of it is taken as its scarcest length allows. The amounts are rounded down, and what rounding
leaves is solved and rounded again while that yields sequences; best fit packs only the rest. Any
prices, divided by the greatest value of a configuration under them, bound the program from below.

All of this works on at most capacity counts, whatever the number of pieces; the plan is then dealt
out to the pieces by their rank within their length.
"""

from __future__ import annotations

import re
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from . import common as c

CAPACITY = 2048
#: The step of the weights, how much more a price is worth by its length's share of a sequence, the lengths that a round
#: prices (half those that lag most, half drawn from all), and the share of the demand that a program serves.
STEP, LONGER, PRICED, SERVED = 0.003, 0.01, 128, 0.9
#: Programs, each on the residue of the one before; rounds of one.
LEVELS, ROUNDS = 6, 6000
#: Words whose ids a worker remembers before it starts anew; rows that are cut into pieces at once.
WORDS_MOST, ROWS = 200_000, 500
#: Texts of these characters alone (Latin letters, no superscripts and fractions) normalise as str.lower does.
PLAIN = r"[\t\n\r\x20-\x7e\xa1-\xb1\xb4-\xb8\xba\xbb\xbf-\u012f\u0131-\u024f]*"
#: The vocabulary's splitting pattern (fixed value), as it reads for such texts.
SPLIT = r"'s|'t|'re|'ve|'m|'ll|'d|[^\W\d_]+|\d|(?:[^\w\s]|_)+"


class WordIds:
    """A text's ids as little-endian 32-bit bytes; equal to the tokenizer's, with a memory of words."""

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.tok = Tokenizer.from_file(path)
        self.known: dict[str, bytes] = {}
        self.plain, self.split = re.compile(PLAIN), re.compile(SPLIT)
        # The byte-level alphabet: printable bytes stand for themselves, the others follow from 256 on.
        own = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or 174 <= b]
        rest = iter(range(256, 512))
        self.alphabet = {b: b if b in own else next(rest) for b in range(256)}

    def whole(self, text: str) -> bytes:
        return np.array(self.tok.encode(text, add_special_tokens=False).ids, dtype="<u4").tobytes()

    def word(self, word: str) -> bytes:
        """One piece of the split, straight from the merges."""
        return np.array([t.id for t in self.tok.model.tokenize(word.encode().decode("latin-1").translate(self.alphabet))], dtype="<u4").tobytes()

    def __call__(self, text: str) -> bytes:
        if "<|" in text or not self.plain.fullmatch(text):
            return self.whole(text)
        words = self.split.findall(text.lower())
        try:
            return b"".join(map(self.known.__getitem__, words))
        except KeyError:
            if len(self.known) > WORDS_MOST:
                self.known.clear()
            for w in set(words):
                if w not in self.known:
                    self.known[w] = self.word(w)
            return b"".join(map(self.known.__getitem__, words))


def tokenizer_path(name: str = "word_bpe_49k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def pieces(documents: DataFrame, path: str | None = None, capacity: int = CAPACITY) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32, part: a document's ids and one id 0, cut where longer than capacity."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        place = path or tokenizer_path()
        ids, part, width = c.per_process(f"words of {place}", lambda: WordIds(place)), TaskContext.get().partitionId(), 4 * capacity
        for batch in batches:
            for at in range(0, batch.num_rows, ROWS):
                b = batch.slice(at, ROWS)
                out = []
                for d, t in zip(b.column("doc_id").to_pylist(), b.column("text").to_pylist(), strict=True):
                    body = ids(t or "") + b"\0\0\0\0"
                    out += [(d, i, i * capacity, len(x := body[j : j + width]) // 4, zlib.crc32(x)) for i, j in enumerate(range(0, len(body), width))]
                cols = list(zip(*out, strict=True))
                yield pa.RecordBatch.from_arrays([pa.array(cols[0], pa.int64()), pa.array(cols[1], pa.int32()), *[pa.array(x, pa.int64()) for x in cols[2:]], pa.array([part] * len(out), pa.int32())], ["doc_id", "piece", "start", "length", "ids_crc32", "part"])

    return documents.select("doc_id", "text").mapInArrow(run, "doc_id long, piece int, start long, length long, ids_crc32 long, part int")


# ---- the program over the histogram ---------------------------------------------------------


def price(values: np.ndarray, limit: np.ndarray, lengths: np.ndarray, capacity: int) -> tuple[dict[int, int], float]:
    """The most valuable configuration of lengths and its value: values[l] for each piece of length l, at most limit[l] of them."""
    best, spare, taken = np.zeros(capacity + 1), np.empty(capacity + 1), []
    for x in lengths.tolist():
        left, many = int(min(limit[x], capacity // x)), 1
        while left > 0:  # copies in powers of two
            n = min(many, left)
            w = n * x
            with_ = np.add(best[: capacity + 1 - w], n * values[x], out=spare[: capacity + 1 - w])
            better = with_ > best[w:]
            np.copyto(best[w:], with_, where=better)
            taken.append((x, n, w, better))
            left, many = left - n, 2 * many
    at = int(best.argmax())
    value, out = float(best[at]), {}
    for x, n, w, better in reversed(taken):
        if at >= w and better[at - w]:
            out[x] = out.get(x, 0) + n
            at -= w
    return out, value


def solve(hist: np.ndarray, capacity: int, served: float = SERVED, rounds: int = ROUNDS) -> tuple[list[tuple[dict[int, int], float]], np.ndarray]:
    """Amounts of configurations that together serve a share of hist and no more than it; and the last prices."""
    rng = np.random.default_rng(1)
    lengths, need = np.flatnonzero(hist), hist.astype(float)
    share = np.arange(capacity + 1) / capacity
    got, total, amounts = np.zeros(capacity + 1), float((need * share).sum()), {}
    values = share * (1 + LONGER * share)
    for _ in range(rounds):
        left = need - got
        now = lengths[left[lengths] >= 1 - 1e-9]
        done = float((got * share).sum()) / total if total else 1.0
        if done > served or not len(now):
            break
        values = share * (1 + LONGER * share) * np.exp(-STEP * (got / np.maximum(need, 1) - done))
        if len(now) > PRICED:
            order = now[np.lexsort((rng.random(len(now)), got[now] / need[now]))]
            now = np.sort(np.concatenate([order[: PRICED // 2], rng.choice(order[PRICED // 2 :], PRICED - PRICED // 2, replace=False)]))
        conf, _ = price(values, left + 1e-9, now, capacity)
        amount = min(left[x] / a for x, a in conf.items())
        key = tuple(sorted(conf.items()))
        amounts[key] = amounts.get(key, 0.0) + amount
        for x, a in conf.items():
            got[x] += a * amount
    return [(dict(k), v) for k, v in amounts.items()], values


def lower_bound(hist: np.ndarray, capacity: int, values: np.ndarray | None = None) -> float:
    """The best of three dual bounds on the program: of prices by length, of pieces over half a sequence, and of values."""
    x = np.arange(capacity + 1)
    tried = [x / capacity, (x * 2 > capacity) + 0.5 * (x * 2 == capacity), *([] if values is None else [values])]
    lengths = np.flatnonzero(hist)
    return max(float((hist * y).sum()) / max(price(y, np.full(capacity + 1, capacity), lengths, capacity)[1], 1e-300) for y in tried) if len(lengths) else 0.0


def best_fit(hist: np.ndarray, capacity: int) -> list[tuple[dict[int, int], int]]:
    """Best fit by decreasing length on counts: bins of equal content move together."""
    room: dict[int, list[tuple[dict[int, int], int]]] = {}
    for x in range(capacity, 0, -1):
        n = int(hist[x])
        for r in sorted(k for k in room if k >= x):
            while n and room.get(r):
                content, many = room[r].pop()
                per = r // x
                full = min(many, n // per)
                if many > full:
                    part = n - full * per if full < many else 0
                    used = 0
                    if 0 < part < per:
                        room.setdefault(r - part * x, []).append((content | {x: part}, 1))
                        n, used = n - part, 1
                    if many - full - used:
                        room[r].append((content, many - full - used))
                if full:
                    room.setdefault(r - per * x, []).append((content | {x: per}, full))
                    n -= full * per
                if not full and not n:
                    break
            if not n:
                break
        if n:
            per = capacity // x
            if n // per:
                room.setdefault(capacity - per * x, []).append(({x: per}, n // per))
            if n % per:
                room.setdefault(capacity - n % per * x, []).append(({x: n % per}, 1))
    return [(content, many) for group in room.values() for content, many in group]


def plan(hist: np.ndarray, capacity: int = CAPACITY) -> tuple[list[tuple[dict[int, int], int]], list[tuple[dict[int, int], int]]]:
    """Configurations and how many sequences have each, of the rounded programs and of best fit on what they leave; together they hold hist exactly."""
    left = hist.astype(np.int64).copy()
    rounded: dict[tuple, int] = {((capacity, 1),): int(left[capacity])} if left[capacity] else {}
    left[capacity] = 0
    for _ in range(LEVELS):
        before = len(rounded), sum(rounded.values())
        for conf, amount in sorted(solve(left, capacity)[0], key=lambda x: -x[1]):
            n = min([int(amount + 1e-9), *(int(left[x]) // a for x, a in conf.items())])
            if n > 0:
                key = tuple(sorted(conf.items()))
                rounded[key] = rounded.get(key, 0) + n
                for x, a in conf.items():
                    left[x] -= a * n
        if (len(rounded), sum(rounded.values())) == before:
            break
    return [(dict(k), n) for k, n in rounded.items()], best_fit(left, capacity)


def _slots(configs: list[tuple[dict[int, int], int]]) -> dict[int, tuple[np.ndarray, ...]]:
    """For each length: first rank, first sequence, pieces a sequence, and offset there, of each configuration that has it."""
    rows: dict[int, list[tuple[int, int, int, int]]] = {}
    ranks: dict[int, int] = {}
    base = 0
    for conf, n in configs:
        at = 0
        for x, a in sorted(conf.items(), reverse=True):
            rows.setdefault(x, []).append((ranks.get(x, 0), base, a, at))
            ranks[x] = ranks.get(x, 0) + a * n
            at += a * x
        base += n
    return {x: tuple(np.array(v, dtype=np.int64) for v in zip(*r, strict=True)) for x, r in rows.items()}


def pack(documents: DataFrame, path: str | None = None, capacity: int = CAPACITY) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32, sequence_id, offset for every piece of every row of documents.

    Null texts are empty: one piece with the closing id alone. Rows that repeat are packed each for
    itself. An empty table gives an empty result.
    """
    cut = c.written(pieces(documents, path, capacity))
    counts = cut.groupBy("part", "length").agg(F.count("*").alias("n"))
    hist = np.zeros(capacity + 1, dtype=np.int64)
    for r in cut.groupBy("length").agg(F.count("*").alias("n")).collect():  # at most capacity rows
        hist[r["length"]] = r["n"]
    rounded, rest = plan(hist, capacity)
    slots = _slots(rounded + rest)
    before = counts.select("part", "length", (F.sum("n").over(W.partitionBy("length").orderBy("part")) - F.col("n")).alias("before"))
    own = F.row_number().over(W.partitionBy("part", "length").orderBy("doc_id", "piece", "ids_crc32")) - 1
    ranked = cut.withColumn("own", own).join(before, ["part", "length"]).withColumn("rank", F.col("own") + F.col("before")).drop("own", "before", "part")

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            length, rank = b.column("length").to_numpy(), b.column("rank").to_numpy()
            seq, off = np.zeros(len(rank), np.int64), np.zeros(len(rank), np.int64)
            order = np.argsort(length, kind="stable")
            for group in np.split(order, np.flatnonzero(np.diff(length[order])) + 1) if len(order) else ():
                first, base, a, at = slots[int(length[group[0]])]
                i = np.searchsorted(first, rank[group], "right") - 1
                j = rank[group] - first[i]
                seq[group], off[group] = base[i] + j // a[i], at[i] + j % a[i] * length[group]
            cols = [b.column(k) for k in ("doc_id", "piece", "start", "length", "ids_crc32")]
            yield pa.RecordBatch.from_arrays([*cols, pa.array(seq), pa.array(off)], ["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"])

    return ranked.mapInArrow(place, "doc_id long, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long")
