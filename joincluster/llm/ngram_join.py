"""Exact Jaccard join of word n-gram sets by prefix filters under several global token orders.

A set of n shingles with threshold T% can only link with another if both share a token among the
first n - ceil(T n / 100) + 1 tokens of any fixed global order, and at least l tokens among the
first n - ceil(T n / 100) + l. The first order makes the candidate pairs, two further orders must
agree (with l > 1) before any pair is verified. All orders put the shingles that many documents
share last, the most frequent ones at the end, and sort the rest by a seeded hash; the first one by how common their words are before
that. Shingles of common words meet by chance, and more often the larger the corpus is, so a prefix
of shingles of rare words keeps the candidates near the number of texts that do share something.

Equal sets are one class, joined only once. Inside the bucket of a prefix token the members are
first compared with one leader. Only buckets that then hold several components are searched further:
small ones pair by pair, large ones with their members dealt into blocks by component and size, where
only blocks of near sizes and different components meet. A large group of near copies so costs a
star rather than all its pairs, and no link between components is lost.

Until a pair passes all filters only a sketch of its sets moves: 16-bit hashes of the further orders'
prefixes, and a bit a hash slot that holds the parity of the set's shingles there. Two sets differ in
at least as many shingles as their sketches differ in bits, so a pair whose bits differ more than the
threshold allows is out. The sets themselves are read again from their texts for the pairs left.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import common as c

SHINGLE, PERCENT = 4, 85
#: Shared shingles are counted exactly within a task; those seen so often there are named as frequent.
#: The list only shapes the orders: any list gives the same links.
FREQUENT_FROM, FREQUENT_TASK, FREQUENT_MOST = 3, 1 << 16, 1 << 18
#: Words are told apart by a slot of SLOT_BITS bits; so many slots are named as common in a task and in all. They only shape the first order.
SLOT_BITS, COMMON_TASK, COMMON_MOST = 20, 1 << 14, 1 << 17
#: Buckets of at most FEW sets are searched pair by pair, so pairs grow with the buckets' rows; larger ones by blocks of about BLOCK sets.
FEW, BLOCK = 32, 200
#: Rows (texts, or pairs with their sketches or bodies) that a task hands to Python at once; the default is 10,000.
BATCH = 500
#: Bits a shingle of the sketches in blocks: of sets just under the threshold, most pairs pass one bit a shingle and few pass eight.
FINE = 8


def shingle_sets(texts: pa.Array, size: int) -> Iterator[np.ndarray]:
    """The sorted distinct 64-bit shingle hashes of each text; a text of fewer words is one shingle."""
    return (s for s, _ in _weighed_sets(texts, size, None))


def _weighed_sets(texts: pa.Array, size: int, common: np.ndarray | None) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """shingle_sets, and how common each shingle's words are (0 to 1023), by the classes of common_words; all 0 without them."""
    h, _, first, last = c.word_hashes(texts)
    n = max(0, len(h) - size + 1)
    if common is not None:
        each, sums = common[_slot(h)], np.zeros(n, np.int64)
        for i in range(size):
            sums += each[i : i + n]
        sums = np.minimum(sums, 1023).astype(np.uint64)
    with np.errstate(over="ignore"):
        all_ = h[:n].copy()
        for i in range(1, size):
            all_ = all_ * np.uint64(0x9E3779B97F4A7C15) + h[i : i + n]
        all_ = c.mixed(all_, 100)
        for lo, hi in zip(first.tolist(), last.tolist(), strict=True):
            if hi - lo >= size:
                s = all_[lo : hi - size + 1]
                if common is not None:
                    at = np.argsort(s)
                    s, w = s[at], sums[lo : hi - size + 1][at]
                else:
                    s, w = np.sort(s), np.zeros(len(s), np.uint64)
                keep = np.empty(len(s), bool)
                keep[0] = True
                np.not_equal(s[1:], s[:-1], out=keep[1:])
                yield s[keep], w[keep]
            elif hi > lo:
                w = h[lo:hi] * np.arange(3, 3 + 2 * (hi - lo), 2, dtype=np.uint64)
                yield c.mixed(np.array([np.bitwise_xor.reduce(c.mixed(w, hi - lo))]), 101 + hi - lo), np.zeros(1, np.uint64)
            else:
                yield np.empty(0, np.uint64), np.empty(0, np.uint64)


def _lists(arrays: list[np.ndarray]) -> pa.Array:
    ends = np.cumsum([0, *map(len, arrays)], dtype=np.int32)
    flat = np.concatenate(arrays) if arrays else np.empty(0, np.uint64)
    return pa.ListArray.from_arrays(pa.array(ends), pa.array(flat.view(np.int64)))


def set_hash(s: np.ndarray) -> int:
    import xxhash

    return int(np.uint64(xxhash.xxh3_64_intdigest(s.tobytes())).view(np.int64))


def _slot(words: np.ndarray) -> np.ndarray:
    return (words >> np.uint64(64 - SLOT_BITS)).astype(np.int64)


def _texts(documents: DataFrame) -> DataFrame:
    """The texts of documents in few partitions, for counts of which each task returns a list."""
    parts = max(1, documents.sparkSession.sparkContext.defaultParallelism * 2)
    read = documents.select("text")
    many = read.rdd.getNumPartitions()
    return read.coalesce(max(parts, many // 8)) if many > 4 * parts else read


def common_words(documents: DataFrame) -> np.ndarray:
    """A class for each slot of words, 0 for rare ones and up to 63, four to each doubling of the slot's count over all documents."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n = np.zeros(1 << SLOT_BITS, np.int64)
        for b in batches:
            for at in range(0, b.num_rows, 500):
                n += np.bincount(_slot(c.word_hashes(b.column("text").slice(at, 500))[0]), minlength=len(n))
        most = np.argsort(-n, kind="stable")[: min(COMMON_TASK, np.count_nonzero(n))]
        yield pa.RecordBatch.from_arrays([pa.array(most), pa.array(n[most])], ["slot", "n"])

    top = _texts(documents).mapInArrow(count, "slot long, n long").groupBy("slot").agg(F.sum("n").alias("n")).orderBy(F.desc("n"), "slot").limit(COMMON_MOST).toArrow()
    n, out = top.column("n").to_numpy(), np.zeros(1 << SLOT_BITS, np.uint8)
    if len(n):
        out[top.column("slot").to_numpy()] = np.minimum(1 + np.round(4 * np.log2(n / n.min())), 63)
    return out


def frequent_shingles(documents: DataFrame, size: int = SHINGLE, common: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """At most FREQUENT_MOST shingles that many documents share, sorted, from exact counts within each task, and a class of each (1 to 31), one to
    a doubling of its count. Of each document the half of rarer words is counted; the others come late by their words.
    """

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept = np.empty(0, np.uint64), np.empty(0, np.int64)
        held: list[np.ndarray] = []
        most = 1_500_000

        def merge():
            v = np.concatenate(held)
            held.clear()
            v.sort()
            v, n = np.unique(v[:-1][v[1:] == v[:-1]], return_counts=True)
            n += 1  # of a shingle's places all but one equal the next
            v, at = np.unique(np.concatenate([kept[0], v]), return_inverse=True)
            n = np.bincount(at, weights=np.concatenate([kept[1], n]), minlength=len(v)).astype(np.int64)
            best = np.argsort(-n, kind="stable")[:FREQUENT_TASK]
            return v[best], n[best]

        total = 0
        for b in batches:
            for at in range(0, b.num_rows, 500):
                for s, w in _weighed_sets(b.column("text").slice(at, 500), size, common):
                    if len(s) > 1:
                        s = s[w <= np.partition(w, len(w) // 2)[len(w) // 2]]
                    held.append(s)
                    total += len(s)
                    if total > most:
                        kept, total = merge(), 0
        if held:
            kept = merge()
        yield pa.RecordBatch.from_arrays([pa.array(kept[0].view(np.int64)), pa.array(kept[1])], ["shingle", "n"])

    top = (
        _texts(documents).mapInArrow(count, "shingle long, n long").groupBy("shingle").agg(F.sum("n").alias("n")).where(F.col("n") >= FREQUENT_FROM)
        .orderBy(F.desc("n"), "shingle").limit(FREQUENT_MOST).toArrow()
    )
    s, n = top.column("shingle").to_numpy().view(np.uint64), top.column("n").to_numpy()
    at = np.argsort(s)
    return s[at], np.minimum(np.log2(np.maximum(n[at], 2)), 31).astype(np.uint8)


def _prefix(s: np.ndarray, order: int, length: int, late: np.ndarray) -> np.ndarray:
    length = min(length, len(s))
    if length in (0, len(s)):
        return s[:length]
    rank = (c.mixed(s, order) >> np.uint64(15)) | late
    return s[np.argpartition(rank, length - 1)[:length]]


def _late(s: np.ndarray, frequent: np.ndarray, classes: np.ndarray | None = None) -> np.ndarray:
    """The high bits that put frequent shingles last in every order, by their classes if there are any."""
    if not len(s) or not len(frequent):
        return np.zeros(len(s), np.uint64)
    i = np.minimum(np.searchsorted(frequent, s), len(frequent) - 1)
    return np.where(frequent[i] == s, 1 if classes is None else classes[i], 0).astype(np.uint64) << np.uint64(59)


def _first(n: int, percent: int) -> int:
    return n - -(-percent * n // 100) + 1 if n else 0


def _hashes16(tokens: np.ndarray) -> bytes:
    return np.sort((tokens >> np.uint64(13)).astype(np.uint16)).tobytes()


def _slots(n: int) -> int:
    """Bits of a set's sketch: the power of two from n on."""
    return max(64, 1 << (n - 1).bit_length())


def parity(s: np.ndarray, per: int = 1) -> bytes:
    """A set's sketch: the parity of the number of its hashes in each slot, at least per slots a hash."""
    bits = _slots(per * len(s))
    return np.packbits(np.bincount((s & np.uint64(bits - 1)).astype(np.int64), minlength=bits) & 1 == 1, bitorder="little").tobytes()


def _bits_differ(x: bytes, y: bytes) -> int:
    """In how many bits two sketches differ; the longer is folded onto the shorter, which keeps parities."""
    a, b = np.frombuffer(x, np.uint8), np.frombuffer(y, np.uint8)
    while len(a) > len(b):
        a = a[: len(a) // 2] ^ a[len(a) // 2 :]
    while len(b) > len(a):
        b = b[: len(b) // 2] ^ b[len(b) // 2 :]
    return int(np.bitwise_count(a ^ b).sum())


def _least(n: int, percent: int) -> int:
    return max(1, _first(n, percent) // 2)


def _read(documents: DataFrame, frequent: tuple[np.ndarray, np.ndarray], common: np.ndarray, size: int, percent: int) -> DataFrame:
    """doc_id, row, n, set (hash of the set, null if empty), p1 (prefix under the first order), e2, e3 (longer ones of two further orders, as 16-bit hashes), bits."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 1000):
                b = batch.slice(at, 1000)
                ns, sets, out, e2, e3, bits = [], [], [], [], [], []
                for s, w in _weighed_sets(b.column("text"), size, common):
                    n, late = len(s), _late(s, *frequent)
                    first, more = _first(n, percent), _least(n, percent) - 1
                    ns.append(n)
                    sets.append(set_hash(s) if n else None)
                    out.append(_prefix(s, 0, first, late | w << np.uint64(49)))
                    e2.append(_hashes16(_prefix(s, 1, first + more, late)) if n else None)
                    e3.append(_hashes16(_prefix(s, 2, first + more, late)) if n else None)
                    bits.append(parity(s) if n else None)
                yield pa.RecordBatch.from_arrays(
                    [b.column("doc_id").cast(pa.int64()), b.column("row"), pa.array(ns, pa.int64()), pa.array(sets, pa.int64()), _lists(out), *[pa.array(x, pa.binary()) for x in (e2, e3, bits)]],
                    ["doc_id", "row", "n", "set", "p1", "e2", "e3", "bits"],
                )

    return documents.select("doc_id", "row", "text").mapInArrow(run, "doc_id long, row long, n long, set long, p1 array<long>, e2 binary, e3 binary, bits binary")


def _single(rows: DataFrame, many: int) -> DataFrame:
    """rows, written, with one of each set; many is the number of sets, and only where rows repeat are there more."""
    rows = c.written(rows)
    if rows.count() <= many:
        return rows
    out = c.written(rows.dropDuplicates(["set"]))
    c.dropped(rows)
    return out


def _rows_of(sets: DataFrame, reps: DataFrame) -> DataFrame:
    """row: the first row of each set of a table (column set)."""
    return c.written(sets.select("set").distinct().join(reps.select("set", "row"), "set").select("row"))


def _sketches(sets: DataFrame, read: DataFrame, reps: DataFrame) -> DataFrame:
    """set, n, e2, e3, bits of the sets of a table (column set); rows of other sets do not move."""
    ids = _rows_of(sets, reps)
    return _single(c.semi(read.select("row", "set", *SKETCH), ids, "row").drop("row"), ids.count())


def _fine(sets: DataFrame, sketches: DataFrame, documents: DataFrame, reps: DataFrame, size: int) -> DataFrame:
    """sketches of the sets of a table (column set), with FINE bits a shingle, from their texts."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column("set"), pa.array([parity(np.frombuffer(x.as_buffer(), np.uint64), FINE) for x in b.column("body")], pa.binary())], ["set", "bits"])

    bodies = _bodies(sets, documents, reps, size)
    out = c.written(sketches.drop("bits").join(bodies.mapInArrow(run, "set long, bits binary"), "set").select("set", *SKETCH))
    c.dropped(bodies)
    return out


def _bodies(sets: DataFrame, documents: DataFrame, reps: DataFrame, size: int) -> DataFrame:
    """set, body (its sorted hashes) of the sets of a table (column set), read again from their texts."""
    ids = _rows_of(sets, reps)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 500):
                got = list(shingle_sets(batch.column("text").slice(at, 500), size))
                yield pa.RecordBatch.from_arrays([pa.array([set_hash(s) if len(s) else None for s in got], pa.int64()), pa.array([s.tobytes() for s in got], pa.binary())], ["set", "body"])

    return _single(c.semi(documents.select("row", "text"), ids, "row").select("text").mapInArrow(run, "set long, body binary"), ids.count())


def _shares(x: np.ndarray, y: np.ndarray) -> int:
    """Size of the intersection of two sorted sets."""
    if len(x) > len(y):
        x, y = y, x
    if not len(x):
        return 0
    i = np.minimum(np.searchsorted(y, x), len(y) - 1)
    return int((y[i] == x).sum())


def _most(n: int, m: int, percent: int) -> int:
    """In how many shingles linked sets of n and m can differ."""
    both = -(-percent * (n + m) // (100 + percent))
    return n + m - 2 * both


def _numbered(x: bytes) -> np.ndarray:
    """Sorted 16-bit hashes with a number each that tells repeated ones apart."""
    v = np.frombuffer(x, np.uint16)
    return v.astype(np.int64) * (1 << 32) + np.arange(len(v)) - np.searchsorted(v, v)


def _near(n: int, m: int, x: bytes, y: bytes, percent: int) -> bool:
    """Whether the sketches of two sets of n and m shingles let them link."""
    return 100 * min(n, m) >= percent * max(n, m) and _bits_differ(x, y) <= _most(n, m, percent)


def _agree(n: int, m: int, ex: tuple[np.ndarray, ...], ey: tuple[np.ndarray, ...], percent: int) -> bool:
    """Whether two sets share enough of both further orders' prefixes."""
    least = min(_least(n, percent), _least(m, percent))
    return all(_shares(x, y) >= least for x, y in zip(ex, ey, strict=True))


SKETCH = ("n", "e2", "e3", "bits")


def _candidates(pairs: DataFrame, sketches: DataFrame, percent: int) -> DataFrame:
    """Those (a, b) of pairs that the sketches' bits and then both further orders let pass."""

    def run(columns: list[str], passes) -> DataFrame:
        def one(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                rows = zip(*(b.column(f"{k}_{x}").to_pylist() for k in columns for x in ("a", "b")), strict=True)
                yield b.select(["a", "b"]).filter(pa.array([passes(*r) for r in rows], pa.bool_()))

        return one

    def step(pairs: DataFrame, columns: list[str], passes) -> DataFrame:
        side = lambda x: sketches.select(F.col("set").alias(x), *[F.col(k).alias(f"{k}_{x}") for k in columns])
        return c.written(pairs.select("a", "b").join(side("a"), "a").join(side("b"), "b").mapInArrow(run(columns, passes), "a long, b long"))

    near = step(pairs, ["n", "bits"], lambda n, m, x, y: _near(n, m, x, y, percent))
    out = step(near, ["n", "e2", "e3"], lambda n, m, x2, y2, x3, y3: _agree(n, m, (_numbered(x2), _numbered(x3)), (_numbered(y2), _numbered(y3)), percent))
    c.dropped(near)
    return out


def _verified(pairs: DataFrame, bodies: DataFrame, percent: int) -> DataFrame:
    """Those (a, b) of pairs whose sets link."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            keep = []
            for x, y in zip(b.column("body_a"), b.column("body_b"), strict=True):
                x, y = np.frombuffer(x.as_buffer(), np.uint64), np.frombuffer(y.as_buffer(), np.uint64)
                both = _shares(x, y)
                keep.append(100 * both >= percent * (len(x) + len(y) - both))
            yield b.select(["a", "b"]).filter(pa.array(keep, pa.bool_()))

    side = lambda x: bodies.select(F.col("set").alias(x), F.col("body").alias(f"body_{x}"))
    return pairs.select("a", "b").join(side("a"), "a").join(side("b"), "b").select("a", "b", "body_a", "body_b").mapInArrow(run, "a long, b long")


def _linked(pairs: DataFrame, documents: DataFrame, reps: DataFrame, size: int, percent: int, links: DataFrame | None = None) -> DataFrame:
    """Those (a, b) of pairs, a written table, whose sets link, with links before them; written, and the pairs and what was read for them go."""
    bodies = _bodies(_ends(pairs), documents, reps, size)
    found = _verified(pairs, bodies, percent)
    out = c.written(found if links is None else links.unionByName(found).distinct())
    c.dropped(pairs, bodies, *([] if links is None else [links]))
    return out


def _ends(pairs: DataFrame) -> DataFrame:
    return pairs.select(F.col("a").alias("set")).unionByName(pairs.select(F.col("b").alias("set")))


def _compare(percent: int, forest: bool = False):
    """The pairs of two blocks' sets, of different components, that pass the further orders and the sketches. As a forest:
    only pairs that join what the pairs before them left apart, so fewer than there are sets.
    """

    def run(table: pa.Table) -> pa.Table:
        joined: dict[int, int] = {}

        def top(x: int) -> int:
            while (y := joined.get(x, x)) != x:
                joined[x] = x = joined.get(y, y)
            return x

        blocks = [table["x"][0].as_py()]
        if table["y"][0].as_py() != blocks[0]:
            blocks.append(table["y"][0].as_py())
        held = []
        for k in blocks:
            t = table.filter(pa.compute.equal(table["block"], k))
            held.append([(i, r, n, (_numbered(x), _numbered(y)), z) for i, r, n, x, y, z in zip(*(t[k].to_pylist() for k in ("set", "root", *SKETCH)), strict=True)])
        out = []
        for at, (i, r, n, e, bits) in enumerate(held[0]):
            for j, q, m, f, other in held[1] if len(held) > 1 else held[0][at + 1 :]:
                if r != q and (not forest or top(r) != top(q)) and _near(n, m, bits, other, percent) and _agree(n, m, e, f, percent):
                    out.append((min(i, j), max(i, j)))
                    if forest:
                        joined[top(r)] = top(q)
        return pa.table({"a": pa.array([x for x, _ in out], pa.int64()), "b": pa.array([x for _, x in out], pa.int64())})

    return run


def _sized(x: str, y: str, percent: int) -> Column:
    return F.least(x, y) * 100 >= F.greatest(x, y) * percent


def _block_pairs(wide: DataFrame, sketches: DataFrame, percent: int, block: int, forest: bool = False, alone: bool = False) -> DataFrame:
    """Candidate pairs inside large buckets (token, set, leader, root, n). A set's home is the leader of its first bucket; a home's
    sets are dealt into blocks by their size band and, where it has many of them, their component. Two blocks meet once, if
    they share a bucket, their bands are next to each other and they do not hold one and the same component alone. With alone,
    blocks only meet themselves; a forest is that of each meeting.
    """
    # Sizes of linked sets are at most one band apart.
    band = F.floor(F.log(F.col("n").cast("double")) / F.lit(float(np.log(100 / percent)) if percent < 100 else 1.0) + F.lit(1e-9)).cast("int")
    home = wide.groupBy("set", "root", "n").agg(F.min("leader").alias("home")).withColumn("band", band)
    roots = home.groupBy("home", "band", "root").agg(F.count("*").alias("many"))
    small = roots.where(F.col("many") < block).groupBy("home", "band").agg(F.ceil(F.sum("many") / block).alias("rest"))
    home = home.join(roots, ["home", "band", "root"]).join(small, ["home", "band"], "left")
    own = F.xxhash64("home", "band", "root", F.pmod(F.xxhash64(F.lit(9), "set"), F.ceil(F.col("many") / block)))
    home = c.written(home.select("set", "root", "band", F.when(F.col("many") >= block, own).otherwise(F.xxhash64(F.lit("rest"), "home", "band", F.pmod(F.xxhash64(F.lit(7), "root"), "rest"))).alias("block")))
    held = c.written(wide.join(home.select("set", "block", "band"), "set").groupBy("token", "block").agg(F.min("root").alias("lo"), F.max("root").alias("hi"), F.min("band").alias("band")))
    if alone:
        meet = c.written(held.where("lo != hi").select(F.col("block").alias("x"), F.col("block").alias("y")).distinct())
        members = sketches.join(home.select("set", "root", "block"), "set")
        return meet.join(members, F.col("x") == F.col("block")).groupBy("x", "y").applyInArrow(_compare(percent, forest), "a long, b long")
    x, y = (held.select("token", F.col("block").alias(k), F.col("lo").alias(f"lo_{k}"), F.col("hi").alias(f"hi_{k}"), F.col("band").alias(f"band_{k}")) for k in ("x", "y"))
    meet = c.written(x.join(y, "token").where("x <= y and abs(band_x - band_y) <= 1 and (lo_x != hi_x or lo_y != hi_y or lo_x != lo_y)").select("x", "y").distinct())
    members = sketches.join(home.select("set", "root", "block"), "set")
    rows = meet.select("x", "y", F.explode(F.array_distinct(F.array("x", "y"))).alias("block")).join(members, "block")
    return rows.groupBy("x", "y").applyInArrow(_compare(percent, forest), "a long, b long")


def _several(buckets: DataFrame, links: DataFrame, reps: DataFrame) -> DataFrame:
    """token, set, leader, root, members, n of the buckets of over two sets that the links leave in several components."""
    root = c.components(links).select(F.col("node").alias("set"), "root")
    wide = buckets.join(root, "set", "left").select("token", "set", "leader", F.coalesce("root", "set").alias("root"))
    several = wide.groupBy("token").agg(F.min("root").alias("lo"), F.max("root").alias("hi"), F.count("*").alias("members")).where("lo != hi and members > 2").select("token", "members")
    return c.written(wide.join(several, "token").join(reps.select("set", "n"), "set"))


def _classes(documents: DataFrame, size: int, percent: int) -> tuple[DataFrame, DataFrame]:
    """_written_classes, in small batches; all that goes through Python is written in it."""
    with c.batches_of(documents.sparkSession, BATCH):
        return _written_classes(documents, size, percent)


def _written_classes(documents: DataFrame, size: int, percent: int) -> tuple[DataFrame, DataFrame]:
    """(doc_id, row, n, set, root) of every row of documents (doc_id, row, text), null roots where there are no links; and the links (a, b) between sets that join them."""
    common = common_words(documents)
    frequent = frequent_shingles(documents, size, common)
    read = c.written(_read(documents, frequent, common, size, percent))
    reps = c.written(read.where("set is not null").groupBy("set").agg(F.min("row").alias("row"), F.min("n").alias("n")))

    tokens = read.where("set is not null").select(F.explode("p1").alias("token"), "set")
    shared = tokens.groupBy("token").agg(F.min("set").alias("leader"), F.max("set").alias("last")).where("leader != last").select("token", "leader")
    buckets = c.written(tokens.join(shared, "token").distinct())
    stars = buckets.where("set != leader").select(F.col("leader").alias("a"), F.col("set").alias("b")).distinct()
    long = lambda k: reps.select(F.col("set").alias(k), F.col("n").alias(f"n_{k}"))
    stars = c.written(stars.join(long("a"), "a").join(long("b"), "b").where(_sized("n_a", "n_b", percent)).select("a", "b"))
    sketches = _sketches(_ends(stars), read, reps)
    near = _candidates(stars, sketches, percent)
    c.dropped(stars, sketches)
    links = _linked(near, documents, reps, size, percent)

    # A large group whose sets do not link with their leader has about as many candidates as pairs of sets. So forests of candidates
    # come first, in each block and then between blocks; what their links join is not compared again.
    wide = _several(buckets, links, reps)
    many = wide.where(F.col("members") > FEW)
    fine = None
    if not many.isEmpty():
        sketches = _sketches(many.select("set"), read, reps)
        fine = _fine(many.select("set"), sketches, documents, reps, size)
        c.dropped(sketches)
    for alone in (True, False):
        many = wide.where(F.col("members") > FEW)
        if fine is None or many.isEmpty():
            break
        near = c.written(_block_pairs(many, fine, percent, BLOCK, forest=True, alone=alone).distinct())
        links = _linked(near, documents, reps, size, percent, links)
        c.dropped(wide)
        wide = _several(buckets, links, reps)
    few = wide.where((F.col("members") <= FEW) & (F.col("set") != F.col("leader")))
    x, y = (few.select("token", F.col("set").alias(k), F.col("n").alias(f"n_{k}"), F.col("root").alias(f"root_{k}")) for k in ("a", "b"))
    pairs = c.written(x.join(y, "token").where("a < b and root_a != root_b").where(_sized("n_a", "n_b", percent)).select("a", "b").distinct())
    many = wide.where(F.col("members") > FEW)
    pairs = c.written(pairs)
    sketches = _sketches(_ends(pairs), read, reps)
    more = _candidates(pairs, sketches, percent)
    c.dropped(pairs, sketches)
    if fine is not None:
        more = c.written(more.unionByName(_block_pairs(many, fine, percent, BLOCK)).distinct())
    links = _linked(more, documents, reps, size, percent, links)

    roots = c.components(links).withColumnRenamed("node", "set")
    out = c.written(read.select("doc_id", "row", "n", "set").join(roots, "set", "left").select("doc_id", "row", "n", "set", F.coalesce("root", "set").alias("root")))
    c.dropped(read, reps, buckets, wide, *([] if fine is None else [fine]))
    return out, links


def _rows(documents: DataFrame) -> DataFrame:
    return documents.withColumn("row", F.xxhash64("doc_id", F.coalesce("text", F.lit(""))))


def near_copies(documents: DataFrame, size: int = SHINGLE, percent: int = PERCENT) -> DataFrame:
    """doc_id, n_shingles, component_id for every row of documents.

    Two rows link when 100 * |intersection| >= percent * |union| of their sets of size-word
    shingles; component_id is the smallest doc_id reachable by links, itself included. A text of
    fewer words is one shingle; null, empty and wordless texts have no shingles and no links.
    Rows that repeat are equal sets and so linked. A row of null doc_id links like any other and has the
    least doc_id of its component that is not null, if any. An empty table gives an empty result.
    """
    found, _ = _classes(_rows(documents.select("doc_id", "text")), size, percent)
    least = found.where("root is not null").groupBy("root").agg(F.min("doc_id").alias("component_id"))
    return found.join(least, "root", "left").select("doc_id", F.col("n").alias("n_shingles"), F.coalesce("component_id", "doc_id").alias("component_id"))


def keep_first(documents: DataFrame, size: int = SHINGLE, percent: int = PERCENT) -> DataFrame:
    """The rows of documents, all columns, of which each component of links keeps one: that of the smallest doc_id (a null id comes last), then of the smallest hash of id and text.

    Of rows that repeat (equal id and text) one stays if the text has a word; rows without words link
    with nothing and all stay. Rows of one id but texts that do not link all stay.
    """
    found, _ = _classes(_rows(documents.select("doc_id", "text")), size, percent)
    key = F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "row")
    first = found.where("root is not null").groupBy("root").agg(F.min(key)["row"].alias("first"))
    linked = c.written(found.join(first, "root").select("row", "first"))
    gone = c.written(linked.where("row != first").select("row").distinct())
    twice = c.written(linked.where("row = first").groupBy("row").count().where("count > 1").select("row"))
    held = documents.withColumn("__row", F.xxhash64("doc_id", F.coalesce("text", F.lit(""))))
    out = c.without(held, gone.withColumnRenamed("row", "__row"), "__row")
    if not twice.isEmpty():
        again = twice.withColumnRenamed("row", "__row")
        out = c.without(out, again, "__row").unionByName(c.semi(out, again, "__row").dropDuplicates(["__row"]))
    return out.select([F.col(f"`{x}`") for x in documents.columns])


ORACLE_SQL = r"""
WITH RECURSIVE w AS (
  SELECT doc_id, list_filter(regexp_split_to_array(translate(coalesce(text,''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w
  FROM documents),
s AS (
  SELECT DISTINCT doc_id, array_to_string(w[i:i+3], ' ') AS g
  FROM (SELECT doc_id, w, unnest(range(1, greatest(len(w)-3, 1)+1)) AS i FROM w WHERE len(w) > 0)),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY 1),
p AS (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS c FROM s a JOIN s b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY 1, 2),
e AS (SELECT x, y FROM p JOIN n nx ON nx.doc_id = x JOIN n ny ON ny.doc_id = y WHERE 100 * c >= 85 * (nx.n + ny.n - c)),
t AS (SELECT x, y FROM e UNION SELECT y, x FROM e),
r(x, y) AS (SELECT x, y FROM t UNION SELECT r.x, t.y FROM r JOIN t ON r.y = t.x),
m AS (SELECT x, min(y) AS y FROM r GROUP BY 1)
SELECT d.doc_id, coalesce(n.n, 0)::BIGINT AS n_shingles, least(d.doc_id, coalesce(m.y, d.doc_id)) AS component_id
FROM documents d LEFT JOIN n ON n.doc_id = d.doc_id LEFT JOIN m ON m.x = d.doc_id
"""
