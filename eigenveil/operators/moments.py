"""Means, scatters and their merges over partitions.

A partial state is (count, mean, scatter) with the scatter of centred products, so a
merge is exact whatever the parts are; each task folds its Arrow batches into one state
and states meet in a tree, eight at a time, so the driver sees one.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

STATE = "part long, n long, mean binary, scatter binary"

#: Bytes of scatters that a task holds before it hands its states on.
HELD = 64 << 20
#: Bytes of doubles of wide rows that are folded at a time.
PIECE = 16 << 20


@dataclass
class Moments:
    n: int
    mean: np.ndarray
    scatter: np.ndarray
    rows: np.ndarray | None = None  # centred, where the scatter comes from these alone

    @classmethod
    def empty(cls, d: int) -> Moments:
        return cls(0, np.zeros(d), np.zeros((d, d)))

    @classmethod
    def of(cls, rows: np.ndarray) -> Moments:
        if not len(rows):
            return cls.empty(rows.shape[1])
        mean = rows.mean(0)
        centred = rows - mean
        return cls(len(rows), mean, centred.T @ centred, centred)

    def covariance(self, ddof: int = 1) -> np.ndarray:
        if self.n <= ddof:
            raise ValueError("too few rows for a covariance")
        return self.scatter / (self.n - ddof)


def merge_pair(a: Moments, b: Moments, rule: str = "exact") -> Moments:
    """The state of both parts together; an empty part changes nothing.

    ``as_printed`` divides the parts' scatters by their own n - 1 before they are added,
    which is not the pooled scatter; it exists so that its error can be measured, and
    cannot take parts of one row.
    """
    if not a.n or not b.n:
        return b if not a.n else a
    n = a.n + b.n
    apart = b.mean - a.mean
    mean = a.mean + apart * (b.n / n)
    between = np.outer(apart, apart) * (a.n * b.n / n)
    if rule == "exact":
        return Moments(n, mean, a.scatter + b.scatter + between)
    if rule == "as_printed":
        if a.n < 2 or b.n < 2:
            raise ValueError("this rule needs two rows in each part")
        return Moments(n, mean, a.scatter / (a.n - 1) + b.scatter / (b.n - 1) + between)
    raise ValueError(f"unknown rule {rule}")


def _folded_into(a: Moments, b: Moments, step: int = 256) -> Moments:
    """The exact ``merge_pair`` in the scatter of ``a``, a few rows at a time."""
    if not a.n or not b.n:
        return b if not a.n else a
    n = a.n + b.n
    apart = b.mean - a.mean
    for at in range(0, len(apart), step):
        rows = a.scatter[at : at + step]
        rows += b.scatter[at : at + step]
        rows += np.outer(apart[at : at + step], apart) * (a.n * b.n / n)
    return Moments(n, a.mean + apart * (b.n / n), a.scatter)


def merge_chain(parts: Iterable[Moments], rule: str = "exact") -> Moments:
    """The first part starts, each further one is folded in."""
    return reduce(lambda a, b: merge_pair(a, b, rule), parts)


def merge_tree(parts: list[Moments], width: int = 2) -> Moments:
    """The same in rounds of ``width``."""
    while len(parts) > 1:
        parts = [merge_chain(parts[i : i + width]) for i in range(0, len(parts), width)]
    return parts[0]


def merge_over_tasks(states: DataFrame, parts: int, width: int = 8) -> DataFrame:
    """M13 over tasks: states of ``parts`` parts, numbered from 0, in rounds of ``width``; one row of state is left.

    A task holds two states at a time, and the driver none.
    """

    def fold(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        name, held = None, None
        for batch in batches:
            for row in (batch.slice(k, 1).to_pylist()[0] for k in range(batch.num_rows)):
                new = _unpack(row["n"], row["mean"], row["scatter"])
                if name is not None and row["part"] != name:
                    yield pa.RecordBatch.from_pylist([_pack(held, name)], schema=_ARROW)
                    held = None
                name, held = row["part"], new if held is None else _folded_into(held, new)
        if held is not None:
            yield pa.RecordBatch.from_pylist([_pack(held, name)], schema=_ARROW)

    def folded(df: DataFrame, tasks: int) -> DataFrame:
        return df.repartition(max(1, tasks), "part").sortWithinPartitions("part", "n").mapInArrow(fold, STATE)

    while True:
        parts = -(-parts // width)
        states = folded(states.withColumn("part", F.floor(F.col("part") / width).cast("long")), parts)
        if parts <= 1:
            return states


def merge_means(parts: Iterable[tuple[int, np.ndarray]]) -> np.ndarray:
    """M9: the mean of all rows from counts and means of the parts."""
    parts = [(n, m) for n, m in parts if n]
    return sum(n * m for n, m in parts) / sum(n for n, _ in parts)


def block(column: pa.Array, kind: pa.DataType = pa.float64()) -> np.ndarray:
    """Doubles, or values of another ``kind``, (rows, length) of a list column whose lists have one length."""
    if not len(column):
        return np.empty((0, 0))
    lengths = np.diff(np.asarray(column.offsets))
    if column.null_count or lengths.min() != lengths.max():
        raise ValueError("vectors must be non-null and of one length")
    return np.asarray(column.flatten().cast(kind)).reshape(len(column), int(lengths[0]))


def _upper(d: int) -> np.ndarray:
    return ~np.tri(d, k=-1, dtype=bool)


def _pack(m: Moments, part: int = 0) -> dict:
    """A state as a row; in place of the scatter its centred rows, where they are fewer numbers."""
    few = m.rows is not None and 2 * m.n < len(m.mean) + 1
    return {"part": part, "n": m.n, "mean": m.mean.tobytes(), "scatter": (m.rows if few else m.scatter[_upper(len(m.mean))]).tobytes()}


def _unpack(n: int, mean: bytes, scatter: bytes) -> Moments:
    mean = np.frombuffer(mean)
    if 2 * n < len(mean) + 1 and len(scatter) == 8 * n * len(mean):
        rows = np.frombuffer(scatter).reshape(n, -1)
        return Moments(n, mean, rows.T @ rows)
    full = np.zeros((len(mean), len(mean)))
    full[_upper(len(mean))] = np.frombuffer(scatter)
    for at in range(0, len(mean), 256):
        rows = slice(at, at + 256)
        full[rows, :at] = full[:at, rows].T
        full[rows, rows] += np.triu(full[rows, rows], 1).T
    return Moments(n, mean, full)


def unpacked(row) -> Moments:
    """The state in a row of ``partials`` or ``merge_over_tasks``."""
    return _unpack(row["n"], bytes(row["mean"]), bytes(row["scatter"]))


_ARROW = pa.schema([("part", pa.int64()), ("n", pa.int64()), ("mean", pa.binary()), ("scatter", pa.binary())])


def partials(df: DataFrame, column: str = "px", part: str | None = None, rows: int = 4096) -> DataFrame:
    """States of each task (and value of ``part``), from one scan: one, or more if a task's parts go over ``HELD``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        states: dict[int, Moments] = {}
        for batch in batches:
            wide = len(batch.column("x")[0].values or ()) if batch.num_rows and batch.column("x")[0].is_valid else 0
            step = min(rows, max(256, PIECE // (8 * max(1, wide))))
            for at in range(0, batch.num_rows, step):
                piece = batch.slice(at, step)
                x = block(piece.column("x"))
                names = np.asarray(piece.column("part"))
                for name in np.unique(names).tolist():
                    new = Moments.of(x if (names == name).all() else x[names == name])
                    if states and name not in states and (len(states) + 1) * new.scatter.nbytes > HELD:
                        yield from given(states)
                    states[name] = _folded_into(states[name], new) if name in states else new
        yield from given(states)

    def given(states: dict[int, Moments]) -> Iterator[pa.RecordBatch]:
        for name in list(states):
            yield pa.RecordBatch.from_pylist([_pack(states.pop(name), name)], schema=_ARROW)

    key = F.col(part).cast("long") if part else F.lit(0).cast("long")
    return df.select(key.alias("part"), F.col(column).alias("x")).mapInArrow(run, STATE)


def _folded(states: DataFrame) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, Moments] = {}
        for batch in batches:
            for row in (batch.slice(k, 1).to_pylist()[0] for k in range(batch.num_rows)):
                new = _unpack(row["n"], row["mean"], row["scatter"])
                held[row["part"]] = _folded_into(held[row["part"]], new) if row["part"] in held else new
        if held:
            yield pa.RecordBatch.from_pylist([_pack(m, name) for name, m in held.items()], schema=_ARROW)

    return states.mapInArrow(run, STATE)


def combined(states: DataFrame, width: int = 8) -> dict[int, Moments]:
    """States merged per part in a tree over tasks; what reaches the driver is one row per part and last task."""
    tasks = states.rdd.getNumPartitions()
    while tasks > width:
        tasks = -(-tasks // width)
        states = _folded(states.repartition(tasks))
    held: dict[int, Moments] = {}
    for row in _folded(states.coalesce(1)).collect():
        held[row["part"]] = _unpack(row["n"], bytes(row["mean"]), bytes(row["scatter"]))
    return held


def moments(df: DataFrame, column: str = "px") -> Moments:
    """Local centring, then exact merges, in one scan."""
    got = combined(partials(df, column))
    if not got:
        raise ValueError("no rows")
    return got[0]


def by_part(df: DataFrame, part: str, column: str = "px") -> list[Moments]:
    """States of the named parts, in the order of their numbers."""
    got = combined(partials(df, column, part))
    return [got[k] for k in sorted(got)]


def mean_face(df: DataFrame, column: str = "px") -> np.ndarray:
    """M8: the mean vector, from sums per task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n, total = 0, None
        for batch in batches:
            x = block(batch.column(0))
            if len(x):
                n, total = n + len(x), x.sum(0) if total is None else total + x.sum(0)
        if n:
            yield pa.RecordBatch.from_pydict({"n": pa.array([n]), "mean": pa.array([(total / n).tobytes()], pa.binary())})

    rows = df.select(column).mapInArrow(run, "n long, mean binary").collect()
    return merge_means((r["n"], np.frombuffer(bytes(r["mean"]))) for r in rows)


def covariance_one_round(df: DataFrame, column: str = "px", ddof: int = 1) -> np.ndarray:
    return moments(df, column).covariance(ddof)


def covariance_two_round(df: DataFrame, column: str = "px", ddof: int = 1) -> np.ndarray:
    """The global mean first, then plain sums of scatters around it (no correction term)."""
    mean = mean_face(df, column)
    sent = df.sparkSession.sparkContext.broadcast(mean)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n, total = 0, np.zeros((len(sent.value),) * 2)
        for batch in batches:
            x = block(batch.column(0))
            if len(x):
                s = x - sent.value
                n, total = n + len(x), total + s.T @ s
        if n:
            yield pa.RecordBatch.from_pylist([_pack(Moments(n, np.zeros(len(total)), total))], schema=_ARROW)

    got = combined(df.select(column).mapInArrow(run, STATE))[0]
    return got.covariance(ddof)


def save(state: Moments, spark: SparkSession, path: str) -> None:
    spark.createDataFrame(pa.Table.from_pylist([_pack(state)], schema=_ARROW)).coalesce(1).write.mode("error").parquet(path)


def load(spark: SparkSession, path: str) -> Moments:
    row = spark.read.parquet(path).first()
    return _unpack(row["n"], bytes(row["mean"]), bytes(row["scatter"]))


def update(state: Moments | None, df: DataFrame, column: str = "px") -> Moments:
    """Fold new rows into a stored state without reading the old ones."""
    new = moments(df, column)
    return new if state is None else merge_pair(state, new)


def long_form(spark: SparkSession, square: np.ndarray, digits: int = 9, name: str = "c") -> DataFrame:
    """(i, j, value) of a square matrix."""
    d = len(square)
    values = np.round(square, digits).ravel() + 0.0
    return spark.createDataFrame(pa.table({"i": pa.array(np.repeat(np.arange(d), d), pa.int64()), "j": pa.array(np.tile(np.arange(d), d), pa.int64()), name: pa.array(values)}))


def vector_form(spark: SparkSession, vector: np.ndarray, digits: int = 9, name: str = "value") -> DataFrame:
    return spark.createDataFrame(pa.table({"idx": pa.array(np.arange(len(vector)), pa.int64()), name: pa.array(np.round(vector, digits) + 0.0)}))
