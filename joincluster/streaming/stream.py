"""Marginals and cells of an event stream. Counts are sums, so with fixed components they merge batch by batch."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from functools import reduce

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.components import ComponentSet
from ..operators.lloyd import Centroids, _pass, update
from ..operators.transport import wasserstein_1d

SCHEMA = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def event_stream(spark: SparkSession, path: str, watermark: str = "2 days", files: int = 1) -> DataFrame:
    """Events from a folder of parquet files, with event time and watermark."""
    s = spark.readStream.schema(SCHEMA).option("maxFilesPerTrigger", files).parquet(path)
    return s.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", watermark)


def deduplicated(events: DataFrame) -> DataFrame:
    return events.dropDuplicatesWithinWatermark(["event_id"])


def stream_marginals(events: DataFrame, column: str, window: str = "1 day", slide: str | None = None) -> DataFrame:
    """start, value, w: a feature's marginal in every tumbling (or sliding) window."""
    w = F.window("ts", window, slide) if slide else F.window("ts", window)
    return events.groupBy(w.alias("window"), F.col(column).cast("string").alias("value")).agg(F.count("*").alias("w")).select(F.col("window.start").alias("start"), "value", "w")


def stream_sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    """user_id, start, n: sessions of each user."""
    return events.groupBy(F.session_window("ts", gap).alias("s"), "user_id").agg(F.count("*").alias("n")).select("user_id", F.col("s.start").alias("start"), "n")


def stream_grid(events: DataFrame, dims: DataFrame, on: tuple[str, str], comps: ComponentSet, columns: dict[str, str], window: str | None = None) -> DataFrame:
    """Cells of a stream joined with a static dimension. columns maps each feature to a column of the joined rows."""
    joined = events.join(F.broadcast(dims) if dims.isStreaming is False else dims, F.col(on[0]) == F.col(on[1]))
    cells = [comps[n].encode(F.col(c)).alias(f"c_{n}") for n, c in columns.items()]
    keys = [F.window("ts", window).alias("window")] if window else []
    return joined.select("ts", *cells).groupBy(*keys, *[f"c_{n}" for n in columns]).agg(F.count("*").alias("w"))


def pairs_within(left: DataFrame, right: DataFrame, key: str, within: str = "1 hour") -> DataFrame:
    """Stream-stream join: rows of right at most `within` after a row of left with the same key."""
    l, r = left.select(F.col(key).alias("k_l"), F.col("ts").alias("ts_l"), F.col("event_id").alias("id_l")), right.select(F.col(key).alias("k_r"), F.col("ts").alias("ts_r"), F.col("event_id").alias("id_r"))
    return l.join(r, F.expr(f"k_l = k_r AND ts_r >= ts_l AND ts_r <= ts_l + interval {within}"))


def user_cells(events: DataFrame, comps: ComponentSet, column: str, feature: str) -> DataFrame:
    """user_id, comp, w: running counts of each user's components, kept as state: one short array a user."""
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    n = comps[feature].size

    def run(key, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        counts = list(state.get[0]) if state.exists else [0] * n
        for f in frames:
            for c, w in f["comp"].value_counts().items():
                counts[int(c)] += int(w)
        state.update((counts,))
        yield pd.DataFrame({"user_id": key[0], "comp": range(n), "w": counts})

    encoded = events.select("user_id", comps[feature].encode(F.col(column)).alias("comp"))
    return encoded.groupBy("user_id").applyInPandasWithState(run, "user_id long, comp int, w long", "counts array<long>", "update", GroupStateTimeout.NoTimeout)


class Refresher:
    """foreachBatch target: merges each batch's cells into the grid and moves the centroids a few sweeps on."""

    def __init__(self, centroids: Centroids, encode: Callable[[DataFrame], DataFrame], sweeps: int = 2):
        self.centroids, self.encode, self.sweeps, self.cells, self.objective = centroids, encode, sweeps, None, None

    def __call__(self, batch: DataFrame, epoch: int) -> None:
        names = [f"c_{s.name}" for s in self.centroids.comps.subspaces]
        new = self.encode(batch).groupBy(*names).agg(F.count("*").alias("w"))
        both = new if self.cells is None else self.cells.unionByName(new).groupBy(*names).agg(F.sum("w").alias("w"))
        kept = both.persist()
        kept.count()
        for _ in range(self.sweeps):
            mass, self.objective = _pass(kept, self.centroids, 2)
            self.centroids = update(self.centroids.comps, self.centroids, mass)
        if self.cells is not None:
            self.cells.unpersist()
        self.cells = kept


def drift(window: DataFrame, reference: DataFrame) -> float:
    """The 1-Wasserstein distance of a window's numeric marginal (x, w) from a reference's."""
    return float(wasserstein_1d(window, reference, 1).first()["wp"] or 0.0)


def run_to_table(df: DataFrame, name: str, mode: str, checkpoint: str) -> DataFrame:
    """Runs a stream over all that is there, into a memory table, and returns it."""
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    q.awaitTermination()
    return df.sparkSession.table(name)


def run_to_files(df: DataFrame, folder: str, checkpoint: str, fold: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """Runs a stream over all that is there and returns fold of its whole result. Each batch's result so far is written by tasks to a folder
    of its own and the last one's is read, so no result comes to the driver.
    """
    spark, last = df.sparkSession, []

    def write(batch: DataFrame, epoch: int) -> None:
        fold(batch).write.mode("overwrite").parquet(f"{folder}/{epoch}")
        last[:] = [epoch]

    q = df.writeStream.foreachBatch(write).outputMode("complete").option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.parquet(f"{folder}/{last[0]}") if last else spark.createDataFrame([], fold(df).schema)


def merged(parts: list[DataFrame]) -> DataFrame:
    """Counts of several batches as one."""
    both = reduce(DataFrame.unionByName, parts)
    return both.groupBy(*[c for c in both.columns if c != "w"]).agg(F.sum("w").alias("w"))
