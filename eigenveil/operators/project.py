"""Scores of images on eigenfaces and images from scores."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .moments import block
from .spectra import EigenModel


def _list(values: np.ndarray) -> pa.Array:
    n, k = values.shape
    return pa.ListArray.from_arrays(pa.array(np.arange(n + 1, dtype=np.int64) * k, pa.int32()), pa.array(values.ravel()))


def mapped(df: DataFrame, column: str, out: str, width_check: int | None, make) -> DataFrame:
    """``df`` without ``column``, with ``out``: rows of ``make()(block)``, batch by batch, no shuffle."""
    rest = [c for c in df.columns if c not in (column, out)]
    quoted = [f"`{c.replace('`', '``')}`" for c in rest]
    schema = ", ".join([*(f"`{f.name.replace('`', '``')}` {f.dataType.simpleString()}" for f in df.select(*quoted).schema.fields), f"`{out}` array<double>"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        work = make()
        for whole in batches:
            at = 0
            while at < whole.num_rows:
                # wide rows come a few at a time
                wide = len(whole.column(column)[at].values or ()) if whole.column(column)[at].is_valid else 0
                batch = whole.slice(at, max(64, (8 << 20) // (8 * max(1, wide))))
                at += batch.num_rows
                x = block(batch.column(column))
                if width_check is not None and x.shape[1] != width_check:
                    raise ValueError(f"vectors have {x.shape[1]} entries, the model has {width_check}")
                yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in rest), _list(work(x))], [*rest, out])

    return df.select(*quoted, column).mapInArrow(run, schema)


def sign_axes(k: int, size: int = 64) -> np.ndarray:
    """Fixed orthonormal axes for audits: entry (i, j) is (-1)**popcount(i AND j) over the root of ``size``."""
    i, j = np.arange(k)[:, None], np.arange(size)[None, :]
    return np.where(np.bitwise_count(i & j) % 2 == 0, 1.0, -1.0) / np.sqrt(size)


def scores(df: DataFrame, model: EigenModel, column: str = "px", out: str = "score", center: bool = True, digits: int | None = None) -> DataFrame:
    """Products with each eigenface; the model goes out once as a broadcast of nc x d numbers.

    ``digits`` rounds the scores, so that a task that runs again in other batches gives the same.
    """
    sent = df.sparkSession.sparkContext.broadcast((model.mean, model.vectors))

    def make():
        mean, vectors = sent.value

        def work(x: np.ndarray) -> np.ndarray:
            got = (x - mean if center else x) @ vectors.T
            return got if digits is None else np.round(got, digits) + 0.0

        return work

    return mapped(df, column, out, len(model.mean), make)


def centred(df: DataFrame, mean: np.ndarray, column: str = "px", out: str = "centred") -> DataFrame:
    sent = df.sparkSession.sparkContext.broadcast(mean)
    return mapped(df, column, out, len(mean), lambda: lambda x: x - sent.value)


def synthesise(df: DataFrame, model: EigenModel, column: str = "score", out: str = "face", add_mean: bool = True) -> DataFrame:
    """The sum of eigenfaces times scores, with the mean face."""
    sent = df.sparkSession.sparkContext.broadcast((model.mean, model.vectors))

    def make():
        mean, vectors = sent.value
        return lambda x: x @ vectors + (mean if add_mean else 0.0)

    return mapped(df, column, out, model.nc, make)


def as_image(column, w: int, h: int):
    """A vector as h rows of whole grey values from 0 to 255; a constant vector becomes zeros."""
    lo, hi = F.array_min(column), F.array_max(column)
    grey = F.transform(column, lambda x: F.when(hi > lo, F.round((x - lo) / (hi - lo) * 255)).otherwise(F.lit(0.0)).cast("int"))
    return F.transform(F.sequence(F.lit(0), F.lit(h - 1)), lambda y: F.slice(grey, y * w + 1, w))
