"""Capture-time release, incremental models, windows and the budget ledger on streams."""

from __future__ import annotations

import json
import os
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..operators import moments
from ..operators.classify import predict
from ..operators.release import PrivateEigenModel

CAPTURE = "id long, label string, w int, h int, ch int, px array<float>, ts timestamp, device string"


def capture(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    """Captured images as they arrive in a folder of Parquet files."""
    return spark.readStream.schema(CAPTURE).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def rate_captures(spark: SparkSession, gallery: DataFrame, rows_per_second: int = 10) -> DataFrame:
    """A load test: rows of the ``rate`` source, each taken for a capture of one of ``gallery``'s images."""
    n = gallery.count()
    ticks = spark.readStream.format("rate").option("rowsPerSecond", rows_per_second).load()
    numbered = gallery.select("label", "w", "h", "ch", "px", (F.row_number().over(Window.orderBy("id")) - 1).cast("long").alias("k"))
    return ticks.withColumn("k", F.pmod("value", F.lit(n))).join(F.broadcast(numbered), "k").select(F.col("value").alias("id"), "label", "w", "h", "ch", "px", F.col("timestamp").alias("ts"), F.lit("rate").alias("device"))


def once_each(captured: DataFrame, late: str = "1 hour") -> DataFrame:
    """One row per capture id within the watermark, so a resent capture is not released again."""
    return captured.withWatermark("ts", late).dropDuplicatesWithinWatermark(["id"])


def perturbed(captured: DataFrame, model: PrivateEigenModel) -> DataFrame:
    """Project, scale and perturb each capture; the noise depends on the id alone, not on the batch."""
    return model.release(captured, keep=("id", "label", "ts", "device")).df


def recognised(released: DataFrame, net) -> DataFrame:
    return predict(released, net)


def run_to_end(stream: DataFrame, path: str, checkpoint: str) -> None:
    """Write what is there and stop."""
    query = stream.writeStream.format("parquet").option("path", path).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    query.awaitTermination()


class IncrementalMoments:
    """foreachBatch sink: folds each batch into a stored state, once per batch id."""

    def __init__(self, spark: SparkSession, path: str, column: str = "px"):
        self.spark, self.path, self.column = spark, path, column

    def current(self) -> tuple[int, moments.Moments | None]:
        try:
            head = self.spark.read.text(f"{self.path}/head").orderBy(F.desc(F.get_json_object("value", "$.batch").cast("long"))).first()
        except Exception as e:  # the folder does not exist before the first batch
            if "PATH_NOT_FOUND" not in str(e):
                raise
            head = None
        if head is None:
            return -1, None
        batch = json.loads(head["value"])["batch"]
        return batch, moments.load(self.spark, f"{self.path}/state-{batch}")

    def __call__(self, df: DataFrame, batch: int) -> None:
        done, state = self.current()
        if batch <= done or df.isEmpty():
            return
        moments.save(moments.update(state, df, self.column), self.spark, f"{self.path}/state-{batch}")
        self.spark.createDataFrame([(json.dumps({"batch": batch}),)], "value string").coalesce(1).write.mode("append").text(f"{self.path}/head")


def counts_by_window(events: DataFrame, size: str, slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """Tumbling or sliding counts per event type; ``ts`` is cast, as the tables have no zone."""
    stamped = events.withColumn("ts", F.col("ts").cast("timestamp"))
    if stamped.isStreaming:
        stamped = stamped.withWatermark("ts", late)
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    return stamped.groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n"), F.sum("value").alias("total")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "event_type", "n", "total")


def visits(events: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    stamped = events.withColumn("ts", F.col("ts").cast("timestamp"))
    if stamped.isStreaming:
        stamped = stamped.withWatermark("ts", late)
    return stamped.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def budget_ledger(releases: DataFrame, cap: float) -> DataFrame:
    """Per identity the running budget; a release that would pass ``cap`` is refused and not counted."""

    def spend(key: tuple, parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        spent = state.get[0] if state.exists else 0.0
        out = []
        for part in parts:
            for release, eps in zip(part["release_id"], part["eps"]):
                fits = spent + eps <= cap + 1e-12
                spent += eps if fits else 0.0
                out.append((key[0], release, eps, spent, bool(fits)))
        state.update((spent,))
        yield pd.DataFrame(out, columns=["id", "release_id", "eps", "spent", "accepted"])

    return releases.groupBy("id").applyInPandasWithState(spend, "id long, release_id string, eps double, spent double, accepted boolean", "spent double", "append", GroupStateTimeout.NoTimeout)


def without_revoked(stream: DataFrame, revoked: DataFrame) -> DataFrame:
    """Stream-static: captures of revoked ids are dropped."""
    return stream.join(F.broadcast(revoked.select("id")), "id", "left_anti")


def capture_to_result(captured: DataFrame, results: DataFrame, within: str = "5 minutes", late: str = "10 minutes") -> DataFrame:
    """Stream-stream: each capture with its result within an interval, and the seconds between."""
    c = captured.withWatermark("ts", late).select("id", F.col("ts").alias("captured"))
    r = results.withWatermark("ts", late).select(F.col("id").alias("rid"), F.col("ts").alias("answered"))
    on = (F.col("id") == F.col("rid")) & (F.col("answered") >= F.col("captured")) & (F.col("answered") <= F.col("captured") + F.expr(f"INTERVAL {within}"))
    return c.join(r, on).select("id", "captured", "answered", (F.unix_timestamp("answered") - F.unix_timestamp("captured")).alias("seconds"))


def write_captures(images: DataFrame, folder: str, files: int, rows: int = 100_000) -> None:
    """FX8: image rows as ``files`` Parquet files (more beyond ``rows`` rows each) with capture times and devices.

    Captures lie in the files in the order of their times, and a file is written after all
    earlier ones: a replay that takes files by their age finds no capture late, however
    long the time that the table spans.
    """
    stamped = images.withColumn("ts", F.timestamp_seconds(F.lit(1_700_000_000) + F.col("id") * 7)).withColumn("device", F.concat(F.lit("cam"), F.pmod("id", F.lit(3))))
    n = images.count()
    files = max(files, -(-n // rows)) if n else 1
    # one file has no quantiles
    ends = sorted({int(x) for x in images.select(F.col("id").cast("double").alias("id")).approxQuantile("id", [k / files for k in range(1, files)], 0.01)}) if files > 1 else []
    place = F.lit(0)
    for end in ends:
        place = place + F.coalesce(F.col("id") > end, F.lit(False)).cast("int")
    for k in range(len(ends) + 1):
        stamped.where(place == k).coalesce(1).write.mode("append").parquet(os.fspath(folder))
