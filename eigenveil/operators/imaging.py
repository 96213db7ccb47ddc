"""Resolution, colour, flattening and flips of image rows."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

KEPT = "id long, label string, w int, h int, ch int, px array<float>"


def min_resolution(df: DataFrame) -> DataFrame:
    """M1: one row with w_min and h_min."""
    return df.agg(F.min("w").alias("w_min"), F.min("h").alias("h_min"))


def split_valid(df: DataFrame, length: int | None = None, column: str = "px") -> tuple[DataFrame, DataFrame]:
    """(usable rows, rejected rows with a reason): null, non-finite or of the wrong length."""
    size = F.lit(length) if length is not None else F.col("w") * F.col("h") * F.col("ch")
    bad = F.exists(column, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    reason = F.when(F.col(column).isNull(), "null").when(F.size(column) != size, "length").when(bad, "not finite")
    marked = df.withColumn("reason", reason)
    return marked.where("reason IS NULL").drop("reason"), marked.where("reason IS NOT NULL")


def resample_nearest(df: DataFrame, irw: int, irh: int) -> DataFrame:
    """M3 with the nearest pixel, as expressions: target (x, y) reads floor((x + 1/2) * w / irw)."""
    n = irw * irh

    def value(i):
        plane, cell = F.floor(i / n), F.pmod(i, F.lit(n))
        y = F.floor((F.floor(cell / irw) * 2 + 1) * F.col("h") / (2 * irh))
        x = F.floor((F.pmod(cell, F.lit(irw)) * 2 + 1) * F.col("w") / (2 * irw))
        return F.get("px", (plane * F.col("w") * F.col("h") + y * F.col("w") + x).cast("int"))

    px = F.transform(F.sequence(F.lit(0), F.lit(n) * F.col("ch") - 1), value)
    return df.withColumn("px", px).withColumn("w", F.lit(irw)).withColumn("h", F.lit(irh))


def _weights(size: int, target: int, kernel: str) -> np.ndarray:
    """(target, size) rows of weights that sum to one."""
    out = np.zeros((target, size))
    scale = size / target
    for t in range(target):
        if kernel == "area":
            lo, hi = t * scale, (t + 1) * scale
            for s in range(int(lo), min(size, int(np.ceil(hi)))):
                out[t, s] = min(hi, s + 1) - max(lo, s)
        else:  # bilinear between the centres of the two nearest pixels
            at = min(max((t + 0.5) * scale - 0.5, 0.0), size - 1.0)
            s = int(at)
            out[t, s] += 1 - (at - s)
            out[t, min(size - 1, s + 1)] += at - s
    return out / out.sum(1, keepdims=True)


def resample(df: DataFrame, irw: int = 47, irh: int = 62, kernel: str = "nearest") -> DataFrame:
    """M3: every image at irw x irh by nearest, bilinear or area sampling."""
    if kernel == "nearest":
        return resample_nearest(df, irw, irh)
    if kernel not in ("bilinear", "area"):
        raise ValueError(f"unknown kernel {kernel}")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known: dict[tuple[int, int], np.ndarray] = {}

        def weights(size: int, target: int) -> np.ndarray:
            if (size, target) not in known:
                known[size, target] = _weights(size, target, kernel)
            return known[size, target]

        for batch in batches:
            out = []
            for w, h, ch, px in zip(*(batch.column(x).to_pylist() for x in ("w", "h", "ch", "px"))):
                planes = np.array(px, np.float64).reshape(ch, h, w)
                out.append((weights(h, irh) @ planes @ weights(w, irw).T).astype(np.float32).ravel().tolist())
            n = batch.num_rows
            yield pa.RecordBatch.from_arrays([batch.column("id"), batch.column("label"), pa.array([irw] * n, pa.int32()), pa.array([irh] * n, pa.int32()), batch.column("ch"), pa.array(out, pa.list_(pa.float32()))], ["id", "label", "w", "h", "ch", "px"])

    return df.select("id", "label", "w", "h", "ch", "px").mapInArrow(run, KEPT)


def to_gray(df: DataFrame) -> DataFrame:
    """The mean of the channels."""
    n = F.col("w") * F.col("h")
    px = F.transform(F.sequence(F.lit(0), n - 1), lambda i: (F.aggregate(F.sequence(F.lit(0), F.col("ch") - 1), F.lit(0.0), lambda s, c: s + F.get("px", (c * n + i).cast("int"))) / F.col("ch")).cast("float"))
    return df.withColumn("px", px).withColumn("ch", F.lit(1))


def stack_channels(df: DataFrame, columns: list[str]) -> DataFrame:
    """Single-channel columns one after the other as one image."""
    return df.withColumn("px", F.concat(*columns)).withColumn("ch", F.lit(len(columns)))


def _let(value, body):
    """``body`` of a value that is worked out once; a name in an earlier projection is worked out at each of its places."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


def standardise(df: DataFrame, mode: str = "none", column: str = "px") -> DataFrame:
    """A record as it is, scaled to [0, 1], or with mean 0 and deviation 1; constant records become zeros."""
    if mode == "none":
        return df
    wide = F.col(column).cast("array<double>")
    if mode == "unit_range":
        return df.withColumn(column, _let(F.array_min(wide), lambda lo: _let(F.array_max(wide), lambda hi: F.transform(wide, lambda x: F.when(hi > lo, (x - lo) / (hi - lo)).otherwise(F.lit(0.0)).cast("float")))))
    if mode == "zscore":
        total = lambda values: F.aggregate(values, F.lit(0.0), lambda s, x: s + x) / F.size(column)
        off = lambda mean: F.transform(wide, lambda x: x - mean)
        spread = lambda d: _let(F.sqrt(total(F.transform(d, lambda x: x * x))), lambda dev: F.transform(d, lambda x: F.when(dev > 0, x / dev).otherwise(F.lit(0.0)).cast("float")))
        return df.withColumn(column, _let(total(wide), lambda mean: _let(off(mean), spread)))
    raise ValueError(f"unknown mode {mode}")


def flatten(df: DataFrame, column: str = "rows") -> DataFrame:
    """M4: a 2-D array column as one vector."""
    return df.withColumn(column, F.flatten(column))


def as_rows(column, w: int, h: int):
    """A flat vector as an array of h rows."""
    return F.transform(F.sequence(F.lit(0), F.lit(h - 1)), lambda y: F.slice(column, y * w + 1, w))


def vertical_flip(df: DataFrame) -> DataFrame:
    """Rows of pixels in reverse order, channel by channel."""
    w, h = F.col("w"), F.col("h")

    def value(i):
        plane, cell = F.floor(i / (w * h)), F.pmod(i, w * h)
        return F.get("px", (plane * w * h + (h - 1 - F.floor(cell / w)) * w + F.pmod(cell, w)).cast("int"))

    return df.withColumn("px", F.transform(F.sequence(F.lit(0), F.size("px") - 1), value))
