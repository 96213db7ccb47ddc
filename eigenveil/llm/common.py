"""Helpers that every training-data operator shares: tables, shared storage, words."""

from __future__ import annotations

import atexit
import ctypes
import re
import shutil
import tempfile
import uuid
from collections.abc import Iterable, Iterator
from contextlib import contextmanager

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: One temporary folder per application, used only where the session names no shared one.
_OWN_DIRS: dict[str, str] = {}
#: Runtime setting (Spark 4.1): shuffle files go when the query that made them ends.
_TIDY = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir``.

    Where it is unset and all executors run in the driver's process, an own temporary
    folder; anywhere else a ValueError, as other machines would not see that folder.
    """
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    if not re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master):
        raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
    app = spark.sparkContext.applicationId
    if app not in _OWN_DIRS:
        _OWN_DIRS[app] = "file://" + tempfile.mkdtemp(prefix="shared-")
        atexit.register(shutil.rmtree, _OWN_DIRS[app].removeprefix("file://"), ignore_errors=True)
    return _OWN_DIRS[app]


def new_path(spark: SparkSession, tag: str) -> str:
    return f"{shared_dir(spark)}/{tag}-{uuid.uuid4().hex}"


@contextmanager
def tidy_shuffles(spark: SparkSession):
    """Within it, a query's shuffle files go as soon as the query ends: what it wrote stays."""
    before = spark.conf.get(_TIDY, "false")
    spark.conf.set(_TIDY, "true")
    try:
        yield
    finally:
        spark.conf.set(_TIDY, before)


def materialise(df: DataFrame, tag: str) -> DataFrame:
    """Write ``df`` as Parquet in the shared folder and read it back, which cuts its lineage.

    The shuffle files behind it are dropped; lost executors cost no more than the write.
    """
    path = new_path(df.sparkSession, tag)
    with tidy_shuffles(df.sparkSession):
        df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def discard(df: DataFrame) -> None:
    """Free the files of a materialised table that nothing reads any more (an empty table takes their place)."""
    for path in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
        df.sparkSession.createDataFrame([], df.schema).write.mode("overwrite").parquet(path)


def byte_texts(column: pa.Array) -> list[bytes | None]:
    """The UTF-8 bytes of a string column, without decoding them."""
    if pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type):
        return column.cast(pa.large_binary()).to_pylist()
    return column.cast(pa.binary()).to_pylist()


def id_bucket(column: str, divisor: int):
    """crc32 of the id as text, modulo ``divisor``; a null id counts as the empty text."""
    return F.crc32(F.coalesce(F.col(column).cast("string"), F.lit("")).cast("binary")) % F.lit(divisor)


def bounded_sample(df: DataFrame, key: str, rows: int) -> DataFrame:
    """About ``rows`` rows (never over 5/4 of it) whose hashed key is small; all rows of a small table."""
    total = df.count()
    if total <= rows:
        return df
    share = min(1.0, 1.1 * rows / total)
    picked = F.pmod(F.xxhash64(F.lit(77), F.col(key)), F.lit(1 << 20)) < F.lit(int(share * (1 << 20)) + 1)
    return df.where(picked).limit(rows * 5 // 4)


class WordHashes(dict):
    """Memo of 64-bit word hashes; it forgets everything when it holds ``limit`` words."""

    def __init__(self, limit: int = 200_000):
        super().__init__()
        self.limit = limit

    def __missing__(self, word: bytes) -> int:
        if len(self) >= self.limit:
            self.clear()
        value = self[word] = xxhash.xxh3_64_intdigest(word)
        return value

    def of(self, words: list[bytes]) -> np.ndarray:
        return np.fromiter(map(self.__getitem__, words), np.uint64, len(words))


def mixed(values: np.ndarray) -> np.ndarray:
    """Bijective 64-bit finaliser (the public splitmix64 constants)."""
    x = values.astype(np.uint64, copy=True)
    x ^= x >> np.uint64(30)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


#: Odd multiplier of rolling window hashes.
_ROLL = 0x9E3779B97F4A7C15


def window_hashes(words: np.ndarray, width: int) -> np.ndarray:
    """A 64-bit hash of each run of ``width`` consecutive word hashes."""
    n = len(words) - width + 1
    if n <= 0:
        return np.empty(0, np.uint64)
    out = np.zeros(n, np.uint64)
    with np.errstate(over="ignore"):
        for j in range(width):
            out *= np.uint64(_ROLL)
            out += words[j : j + n]
    return mixed(out)


def batches_of(rows: Iterable[dict], schema: pa.Schema, size: int = 4096):
    """Record batches of at most ``size`` rows from dictionaries."""
    held: list[dict] = []
    for row in rows:
        held.append(row)
        if len(held) >= size:
            yield pa.RecordBatch.from_pylist(held, schema=schema)
            held = []
    if held:
        yield pa.RecordBatch.from_pylist(held, schema=schema)


def sorted_groups(batches: Iterable[pa.RecordBatch], by: list[str]) -> Iterator[pa.Table]:
    """Tables of the rows that agree in ``by``, from batches in which these stand together."""
    held: list[pa.Table] = []
    for batch in batches:
        now = pa.Table.from_batches([batch])
        if not len(now):
            continue
        values = [np.asarray(now.column(x)) for x in by]
        apart = np.any([x[1:] != x[:-1] for x in values], axis=0)
        cuts = [0, *(np.flatnonzero(apart) + 1).tolist(), len(now)]
        for a, b in zip(cuts, cuts[1:]):
            part = now.slice(a, b - a)
            if held and any(held[-1].column(x)[-1].as_py() != part.column(x)[0].as_py() for x in by):
                yield pa.concat_tables(held)
                held = []
            held.append(part)
    if held:
        yield pa.concat_tables(held)


def trim() -> None:
    """Give memory that a Python worker has freed back to the system, as workers outlive their tasks."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (OSError, AttributeError):  # another C library
        pass


_PER_WORKER: dict = {}


def per_worker(key, make):
    """An object that is built once in each Python worker."""
    if key not in _PER_WORKER:
        _PER_WORKER[key] = make()
    return _PER_WORKER[key]


def with_columns(df: DataFrame, added: str, make, rows: int = 500) -> DataFrame:
    """``df`` with the columns named in the DDL ``added``, which replace columns of these names.

    ``make`` runs once in each task and returns a function from a record batch (of at most
    ``rows`` rows) to the arrays of the new columns.
    """
    names = [x.split()[0] for x in added.split(", ")]
    df = df.drop(*names)

    def run(batches):
        work = make()
        for batch in batches:
            for at in range(0, batch.num_rows, rows):
                part = batch.slice(at, rows)
                yield pa.RecordBatch.from_arrays([*part.columns, *work(part)], [*part.schema.names, *names])
        del work
        trim()

    kept = ", ".join(f"`{f.name.replace('`', '``')}` {f.dataType.simpleString()}" for f in df.schema.fields)
    return df.mapInArrow(run, f"{kept}, {added}" if kept else added)
