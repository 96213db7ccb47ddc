"""Min-max scaling of score vectors to [0, 1]."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import vec_scale01
from .moments import block


@dataclass
class Bounds:
    scope: str
    lo: np.ndarray | None = None
    hi: np.ndarray | None = None


def fit_bounds(df: DataFrame, column: str = "score", scope: str = "component", public: tuple[float, float] | None = None, nc: int | None = None) -> Bounds:
    """Bounds per component, over all components, per record (no fit) or stated publicly."""
    if scope == "record":
        return Bounds(scope)
    if scope == "public":
        return Bounds(scope, np.full(nc, float(public[0])), np.full(nc, float(public[1])))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lo = hi = None
        for batch in batches:
            x = block(batch.column(0))
            if len(x):
                a, b = x.min(0), x.max(0)
                lo, hi = (a, b) if lo is None else (np.minimum(lo, a), np.maximum(hi, b))
        if lo is not None:
            yield pa.RecordBatch.from_pydict({"lo": pa.array([lo.tobytes()], pa.binary()), "hi": pa.array([hi.tobytes()], pa.binary())})

    rows = df.select(column).mapInArrow(run, "lo binary, hi binary").collect()
    lo = np.min([np.frombuffer(bytes(r["lo"])) for r in rows], 0)
    hi = np.max([np.frombuffer(bytes(r["hi"])) for r in rows], 0)
    if scope == "global":
        lo, hi = np.full(len(lo), lo.min()), np.full(len(hi), hi.max())
    elif scope != "component":
        raise ValueError(f"unknown scope {scope}")
    return Bounds(scope, lo, hi)


def scaled(column, bounds: Bounds, clip: bool = True) -> Column:
    """The scaled vector as an expression; constant indexes become 0.5."""
    column = F.col(column) if isinstance(column, str) else column
    if bounds.scope == "record":
        lo, hi = F.array_min(column), F.array_max(column)
        return F.transform(column, lambda x: F.when(hi > lo, (x - lo) / (hi - lo)).otherwise(F.lit(0.5)))
    return vec_scale01(column, F.array(*map(F.lit, bounds.lo.tolist())), F.array(*map(F.lit, bounds.hi.tolist())), clip)
