"""Structured Streaming forms: windows, dedup, online selection and micro-batch packing."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from curator.operators.kmeans import Centroids, nearest
from curator.operators.packing import dynamic_pack, form_batches, global_rank
from curator.sources.checkpoints import shared_folder


def event_stream(spark: SparkSession, path: str) -> DataFrame:
    """A replay of an event table with ``ts`` as a timestamp."""
    schema = spark.read.parquet(path).schema
    # A single file is streamed through its folder and a name filter.
    folder, _, name = path.rpartition("/")
    return spark.readStream.schema(schema).option("pathGlobFilter", name).parquet(folder).withColumn("ts", F.col("ts").cast("timestamp"))


def drain(stream: DataFrame, mode: str = "complete") -> DataFrame:
    """Runs a stream to the end of what is there and returns its result table, which is kept in files of the shared folder, not by the driver.

    Each micro-batch has a folder of its own that a repeated one replaces; of ``complete`` results the last counts.
    """
    spark = stream.sparkSession
    base, done = f"{shared_folder(spark)}/flow-{uuid.uuid4().hex}", {}

    def keep(rows: DataFrame, epoch: int) -> None:
        rows.write.mode("overwrite").parquet(f"{base}/out/epoch={epoch}")
        done[epoch] = f"{base}/out/epoch={epoch}"

    query = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{base}/state").foreachBatch(keep).trigger(availableNow=True).start()
    query.awaitTermination()
    paths = [done[e] for e in sorted(done)]
    if not paths:
        return spark.createDataFrame([], stream.schema)
    return spark.read.schema(stream.schema).parquet(*(paths[-1:] if mode == "complete" else paths))


def windowed(events: DataFrame, kind: str, size: str, slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """Counts and sums per event type: ``tumbling``, ``sliding`` or ``session`` windows."""
    window = {"tumbling": lambda: F.window("ts", size), "sliding": lambda: F.window("ts", size, slide), "session": lambda: F.session_window("ts", size)}[kind]()
    rows = events.withWatermark("ts", late).groupBy(window.alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("value"), 4).alias("total"))
    return rows.select(F.col("w.start").cast("timestamp_ntz").alias("start_ts"), "event_type", "n", "total")


def deduplicated(events: DataFrame, keys: list[str], late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(keys)


def interval_join(left: DataFrame, right: DataFrame, within: str, late: str = "1 hour") -> DataFrame:
    """Rows of ``right`` (same user) up to ``within`` after a row of ``left``."""
    a = left.withWatermark("ts", late).select(F.col("user_id"), F.col("event_id").alias("left_id"), F.col("ts").alias("left_ts"))
    b = right.withWatermark("ts", late).select(F.col("user_id").alias("u"), F.col("event_id").alias("right_id"), F.col("ts").alias("right_ts"))
    return a.join(b, (F.col("user_id") == F.col("u")) & (F.col("right_ts") > F.col("left_ts")) & (F.col("right_ts") <= F.col("left_ts") + F.expr(f"INTERVAL {within}"))).select("left_id", "right_id")


def with_reference(events: DataFrame, reference: DataFrame, key: str = "user_id") -> DataFrame:
    """A stream joined to a table that does not change, read anew by every micro-batch; rows without a match keep nulls.  Stateless."""
    return events.join(reference, key, "left")


def online_selection(scored: DataFrame, centroids: Centroids, cutoffs: dict[int, float]) -> DataFrame:
    """A stream of ``sample_id, v, ifd`` filtered by the cut-offs per cluster of the last batch fit; stateless."""
    cut = F.element_at(F.create_map(*(F.lit(x) for kv in sorted(cutoffs.items()) for x in kv)), F.col("cluster_id"))
    near = scored.select("sample_id", "ifd", F.explode(F.array(nearest(F.col("v"), centroids))).alias("ds"))
    return near.select("sample_id", (F.array_position("ds", F.array_min("ds")) - 1).cast("int").alias("cluster_id"), "ifd").filter(F.col("ifd") >= cut)


def pack_micro_batches(sink: Callable[[DataFrame, int], None], context: int = 4096, size: int = 256, carry: str | None = None) -> Callable[[DataFrame, int], None]:
    """For ``foreachBatch``: packs each micro-batch in groups of ``size`` and hands the rows to ``sink``.

    With a folder ``carry`` only whole groups are packed; the samples left over wait there for the next micro-batch, in a file per micro-batch, so
    that a repeated one finds what it found before.
    """

    def run(rows: DataFrame, epoch: int) -> None:
        rows = rows.select("sample_id", F.col("n_tokens").cast("int").alias("n_tokens"))
        if carry is not None:
            if epoch:
                rows = rows.unionByName(rows.sparkSession.read.parquet(f"{carry}/epoch={epoch - 1}"))
            ranked = global_rank(rows, F.col("sample_id"), [])
            whole = ranked.count() // size * size
            ranked.filter(F.col("rank") >= whole).drop("rank").write.mode("overwrite").parquet(f"{carry}/epoch={epoch}")
            rows = ranked.filter(F.col("rank") < whole).drop("rank")
        sink(dynamic_pack(form_batches(rows, size), context), epoch)

    return run


class PackBuffer:
    """For ``transformWithStateInPandas``: holds samples of a key until ``SIZE`` are there or ``WAIT_MS`` have passed, then emits one batch.

    Input: ``sample_id, n_tokens`` per key; output: ``key, batch, sample_id, n_tokens``.
    """

    SIZE, WAIT_MS = 256, 60_000

    def init(self, handle) -> None:
        self.handle = handle
        self.held = handle.getListState("held", "sample_id long, n_tokens int")
        self.serial = handle.getValueState("serial", "n long")

    def _emit(self, key, rows):
        import pandas as pd

        serial = self.serial.get()[0] if self.serial.exists() else 0
        self.serial.update((serial + 1,))
        return pd.DataFrame({"key": [key[0]] * len(rows), "batch": [serial] * len(rows), "sample_id": [r[0] for r in rows], "n_tokens": [r[1] for r in rows]})

    def handleInputRows(self, key, rows, timers):
        held = [tuple(r) for r in self.held.get()]
        for frame in rows:
            held += list(zip(frame["sample_id"].tolist(), frame["n_tokens"].tolist(), strict=True))
        while len(held) >= self.SIZE:
            yield self._emit(key, held[: self.SIZE])
            held = held[self.SIZE :]
        self.held.put(held) if held else self.held.clear()
        if held:
            self.handle.registerTimer(timers.getCurrentProcessingTimeInMs() + self.WAIT_MS)

    def handleExpiredTimer(self, key, timers, expired):
        held = [tuple(r) for r in self.held.get()]
        self.held.clear()
        if held:
            yield self._emit(key, held)

    def close(self) -> None:
        pass


def drift(assigned: DataFrame, reference: dict[int, float], window: str = "1 day") -> DataFrame:
    """``start_ts, tv``: total variation between the cluster shares of each window of ``ts, cluster_id`` and the reference shares (batch or a micro-batch)."""
    counts = assigned.groupBy(F.window("ts", window)["start"].alias("start_ts")).agg(*(F.count_if(F.col("cluster_id") == c).alias(f"c{c}") for c in reference), F.count(F.lit(1)).alias("n"))
    gap = sum((F.abs(F.col(f"c{c}") / F.col("n") - p) for c, p in reference.items()), F.lit(0.0))
    return counts.select("start_ts", (gap / 2).alias("tv"))
