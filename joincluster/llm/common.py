"""Shared pieces of the corpus operators: tables, the shared folder, text rules, hashing, components.

Every operator here takes and returns DataFrames, tolerates extra columns (it selects what it
needs by name first) and treats a null text as the empty text unless its docstring says otherwise.
"""

from __future__ import annotations

import sys
import tempfile
import types
import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager
from typing import TypeVar

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

T = TypeVar("T")
UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
LOWER = UPPER.lower()
#: bytes.translate table that lower-cases A-Z and leaves every other byte.
FOLD = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))


def per_process(key: str, make: Callable[[], T]) -> T:
    """A value that the tasks of one Python worker share, such as a tokenizer and its memory of words."""
    held = sys.modules.setdefault("_joincluster_held", types.ModuleType("_joincluster_held")).__dict__
    if key not in held:
        held[key] = make()
    return held[key]


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir. Only a local master, as in tests, gets an own one where it is unset."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not found:
        if not spark.sparkContext.master.startswith("local["):
            raise ValueError("spark.checkpoint.dir is unset: executors need a folder that all of them can read")
        spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="joincluster-"))
        found = spark.sparkContext.getCheckpointDir()
    return found


def written(df: DataFrame) -> DataFrame:
    """df, written to the shared folder and read again: the lineage is cut and an executor's loss costs one read.

    The files go when the driver's JVM ends.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/joincluster-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    jvm = spark.sparkContext._jvm
    place = jvm.org.apache.hadoop.fs.Path(path)
    place.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).deleteOnExit(place)
    jvm.System.gc()  # Spark removes the shuffle files of finished plans once the driver's garbage is collected
    out = spark.read.schema(df.schema).parquet(path)
    out._written_at = path
    return out


def dropped(*tables: DataFrame) -> None:
    """Removes tables that written() made, once nothing will read them again."""
    for df in tables:
        spark, place = df.sparkSession, df.sparkSession.sparkContext._jvm.org.apache.hadoop.fs.Path(df._written_at)
        place.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(place, True)


@contextmanager
def batches_of(spark: SparkSession, rows: int) -> Iterator[None]:
    """Plans that run meanwhile hand at most so many rows at once to Python (fewer if the session's setting is lower): an executor holds each task's batch twice, in its JVM and in the worker."""
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    was = int(spark.conf.get(name))
    spark.conf.set(name, str(rows if was <= 0 else min(was, rows)))
    try:
        yield
    finally:
        spark.conf.set(name, str(was))


#: Numbers that are broadcast as a list at most; longer lists are joined.
LISTED = 1 << 18


def listed(ids: DataFrame) -> DataFrame:
    """A written table of a few numbers a row, marked for broadcast if it is short enough."""
    return F.broadcast(ids) if ids.count() <= LISTED else ids


def fold(text: Column) -> Column:
    """Null becomes empty; A-Z become a-z, nothing else changes."""
    return F.translate(F.coalesce(text, F.lit("")), UPPER, LOWER)


def remainder(doc_id: Column, by: int) -> Column:
    """crc32 of the id's decimal text, modulo by."""
    return F.crc32(doc_id.cast("string").cast("binary")) % F.lit(by)


def with_sql(df: DataFrame, **exprs: str) -> DataFrame:
    return df.withColumns({k: F.expr(v) for k, v in exprs.items()})


# ---- word hashing for the Arrow operators -------------------------------------------------

_FOLDED = np.frombuffer(FOLD, np.uint8)
_BLANK = np.isin(np.arange(256), [9, 10, 11, 12, 13, 32])
#: An odd multiplier (fixed value).
_R = 0x9E3779B97F4A7C15
#: Bytes that are hashed at once; longer texts go in stretches that end at white space. Their length is most of what a worker holds while it hashes.
STRETCH = 1 << 17


def _powers(n: int) -> list[np.ndarray]:
    """Powers of the multiplier and of its inverse modulo 2^64, at least n of each; grown when a longer stretch comes."""
    held = per_process("powers", list)
    if not held or len(held[0]) < n:
        n = max(n, STRETCH + 1)
        held.clear()
        for r in (_R, pow(_R, -1, 1 << 64)):
            x = np.full(n, r, np.uint64)
            x[0] = 1
            with np.errstate(over="ignore"):
                held.append(np.cumprod(x, dtype=np.uint64))
    return held


def _stretch(raw: np.ndarray, opens: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Hashes, starts and ends of the words of raw; opens marks the places where a text begins."""
    low = _FOLDED[raw]
    word = ~_BLANK[raw]
    edge = np.empty(len(raw) + 1, bool)
    edge[0] = edge[-1] = True
    edge[1:-1] = ~word[:-1] | opens[1:]
    starts = np.flatnonzero(word & edge[:-1])
    after = np.empty(len(raw), bool)
    after[-1] = True
    after[:-1] = ~word[1:] | opens[1:]
    ends = np.flatnonzero(word & after) + 1
    up, down = _powers(len(raw) + 1)
    with np.errstate(over="ignore"):
        sums = np.zeros(len(raw) + 1, np.uint64)
        np.cumsum((low.astype(np.uint64) + np.uint64(1)) * up[: len(raw)], out=sums[1:])
        h = (sums[ends] - sums[starts]) * down[starts]
        h = mixed(h ^ ((ends - starts).astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93)), 50)
    return h, starts, ends


def word_hashes(texts: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Of a column of texts: 64-bit hashes of all words (runs without ASCII white space, A-Z lower-cased), each
    word's last three bytes as a number, and where each text's words begin and end in them. Null is empty.
    """
    texts = texts.cast(pa.large_binary())
    at = np.frombuffer(texts.buffers()[1], np.int64)[texts.offset : texts.offset + len(texts) + 1]
    body = texts.buffers()[2]
    raw = np.frombuffer(body, np.uint8)[at[0] : at[-1]] if body is not None and len(at) else np.empty(0, np.uint8)
    at = at - at[0] if len(at) else np.zeros(1, np.int64)
    opens = np.zeros(len(raw) + 1, bool)
    opens[at] = True
    hs, ss, tails = [], [], []
    lo = 0
    while lo < len(raw):
        hi = min(lo + STRETCH, len(raw))
        if hi < len(raw):
            cut = np.flatnonzero(_BLANK[raw[lo:hi]] | opens[lo + 1 : hi + 1])
            while not len(cut) and hi < len(raw):  # one word longer than a stretch
                hi = min(2 * hi - lo, len(raw))
                cut = np.flatnonzero(_BLANK[raw[lo:hi]] | opens[lo + 1 : hi + 1])
            if hi < len(raw):
                hi = lo + int(cut[-1]) + 1
        h, starts, ends = _stretch(raw[lo:hi], opens[lo : hi])
        part = _FOLDED[raw[lo:hi]].astype(np.int64)
        last = np.zeros(len(h), np.int64)
        for i in (1, 2, 3):
            p = ends - i
            last = last * 256 + np.where(p >= starts, part[np.maximum(p, 0)], 0)
        hs.append(h)
        ss.append(starts + lo)
        tails.append(last)
        lo = hi
    h, starts = (np.concatenate(x) if x else np.empty(0, t) for x, t in ((hs, np.uint64), (ss, np.int64)))
    tail = np.concatenate(tails) if tails else np.empty(0, np.int64)
    first = np.searchsorted(starts, at)
    return h, tail, first[:-1], first[1:]


def mixed(x: np.ndarray, seed: int) -> np.ndarray:
    """A second 64-bit hash of 64-bit hashes; each seed gives another order."""
    with np.errstate(over="ignore"):
        x = (x ^ np.uint64((0x9E3779B97F4A7C15 * (seed + 1)) & 0xFFFFFFFFFFFFFFFF)) * np.uint64(0xBF58476D1CE4E5B9)
        x ^= x >> np.uint64(29)
        x = x * np.uint64(0x94D049BB133111EB)
        return x ^ (x >> np.uint64(32))


# ---- bit filters as literals --------------------------------------------------------------

#: A bit filter of more bits than this is not put into a plan; callers then join instead.
FILTER_BITS_MOST = 1 << 24


def filter_bits(n: int, per_key: int = 16, least: int = 1 << 10) -> int:
    bits = least
    while bits < n * per_key:
        bits *= 2
    return bits


def bit_words(hashes: DataFrame, column: str, bits: int, seeds: tuple[int, ...] = (0,)) -> list[int]:
    """The filter of a column of keys as signed 64-bit words; at most bits / 64 rows come to the driver."""
    if bits > FILTER_BITS_MOST:
        raise ValueError(f"a filter of {bits} bits is over the bound of {FILTER_BITS_MOST}")
    at = F.explode(F.array(*[F.pmod(F.xxhash64(F.lit(s), F.col(column)), F.lit(bits)) for s in seeds]))
    rows = (
        hashes.select(at.alias("bit"))
        .groupBy(F.floor(F.col("bit") / 64).cast("int").alias("word"))
        .agg(F.expr("bit_or(shiftleft(1L, cast(bit % 64 as int)))").alias("bits"))
        .collect()
    )
    words = [0] * (bits // 64)
    for r in rows:
        words[r["word"]] = r["bits"]
    return words


def in_filter(key: Column, words: list[int], seeds: tuple[int, ...] = (0,)) -> Column:
    """Whether all bits of the key are set. The filter is one array literal, so it is held once per task."""
    bits = len(words) * 64
    held = F.lit(np.array(words, dtype=np.int64))
    out = F.lit(True)
    for s in seeds:
        at = F.pmod(F.xxhash64(F.lit(s), key), F.lit(bits))
        word = F.element_at(held, (F.floor(at / 64) + 1).cast("int"))
        out = out & (F.getbit(word, (at % 64).cast("int")) == 1)
    return out


def semi(df: DataFrame, ids: DataFrame, key: str) -> DataFrame:
    """The rows of df whose key is in the written table ids; a short list is broadcast, of a longer one a bit filter goes first, so that other rows do not move."""
    return _by_key(df, ids, key)[0]


def without(df: DataFrame, ids: DataFrame, key: str) -> DataFrame:
    """The rows of df whose key (not null) is not in the written table ids; rows that a bit filter of ids rules out do not move."""
    found, rest = _by_key(df, ids, key, "left_anti")
    return found if rest is None else rest.unionByName(found)


def _by_key(df: DataFrame, ids: DataFrame, key: str, how: str = "left_semi") -> tuple[DataFrame, DataFrame | None]:
    many = ids.count()
    if many <= LISTED:
        return df.join(F.broadcast(ids), key, how), None
    bits = filter_bits(many, 8)
    if bits > FILTER_BITS_MOST:
        return df.join(ids, key, how), None
    held = in_filter(F.col(key), bit_words(ids, key, bits, (0, 1)), (0, 1))
    return df.where(held).join(ids, key, how), df.where(~held) if how == "left_anti" else None


# ---- connected components ------------------------------------------------------------------


def components(edges: DataFrame) -> DataFrame:
    """(node, root) for every node of edges (a, b): root is the smallest node of its component.

    Alternates the large-star and small-star steps until no edge changes. Each step groups by node
    with map-side minima and joins back, so a hub's edges are spread by the join's skew handling.
    No edges give an empty table.
    """
    now = written(edges.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u != v").distinct())
    mark = None
    while True:
        both = now.unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).withColumn("m", F.least("u", "m"))
        large = both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u != v").distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low, "u").select(F.explode(F.array(F.struct("u", F.col("m").alias("v")), F.struct(F.col("v").alias("u"), F.col("m").alias("v")))).alias("e")).select("e.u", "e.v").where("u != v").distinct()
        now = written(small)
        seen = now.agg(F.count("*").alias("n"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")).alias("h")).first()
        if (seen["n"], seen["h"]) == mark:
            break
        mark = (seen["n"], seen["h"])
    roots = now.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct()
    return now.select(F.col("u").alias("node"), F.col("v").alias("root")).unionByName(roots)
