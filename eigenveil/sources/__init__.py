"""Inputs: tables, image folders, fixture images made from tables, and sinks."""

from __future__ import annotations

import tempfile
from collections.abc import Iterator
from contextlib import contextmanager

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

#: An image: sides, channels and row-major values.
IMAGE = "id long, label string, w int, h int, ch int, px array<float>"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")


def read(spark: SparkSession, fmt: str, path: str, schema: str | None = None, **options) -> DataFrame:
    """CSV, JSON, ORC, text or Parquet with a stated schema."""
    reader = spark.read.options(**options)
    return (reader.schema(schema) if schema else reader).format(fmt).load(path)


def write(df: DataFrame, fmt: str, path: str, partition_by: list[str] | None = None, mode: str = "error") -> None:
    writer = df.write.mode(mode).format(fmt)
    (writer.partitionBy(*partition_by) if partition_by else writer).save(path)


def shared_folder(spark: SparkSession) -> str:
    """``spark.checkpoint.dir``; where it is unset, a temporary folder in local mode and a ValueError elsewhere."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    if not spark.sparkContext.master.startswith("local["):
        raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
    return "file://" + tempfile.mkdtemp(prefix="eigenveil-")


@contextmanager
def small_batches(spark: SparkSession, size: str = "8m") -> Iterator[None]:
    """Arrow batches of about ``size`` meanwhile: several Python processes of a task hold one or more at a time."""
    key = "spark.sql.execution.arrow.maxBytesPerBatch"
    before = spark.conf.get(key)
    spark.conf.set(key, size)
    try:
        yield
    finally:
        spark.conf.set(key, before)


def bucketed(df: DataFrame, name: str, by: str = "id", buckets: int = 64) -> None:
    """A table of released vectors bucketed by a key, so that joins on it need no exchange."""
    df.write.bucketBy(buckets, by).sortBy(by).saveAsTable(name)


def gallery(df: DataFrame, path: str, by: str = "label") -> None:
    """The store of released vectors, partitioned by person."""
    df.write.partitionBy(by).parquet(path)


def bigram_grid(docs: DataFrame, label: str = "lang", w: int = 47, h: int = 62, chars: int | None = None, channels: int = 1) -> DataFrame:
    """FX1 / FX7: a text as an image; each adjacent pair of its characters (all, or the first ``chars``) adds to one cell.

    With three channels each third of the text gives a grid of its own.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for at in range(0, whole.num_rows, 1024):
                batch = whole.slice(at, 1024)
                n, size = batch.num_rows, w * h * channels
                out = np.zeros((n, channels, w * h), np.float32)
                for k, text in enumerate(batch.column("text").to_pylist()):
                    codes = np.frombuffer((text or "").lower()[:chars].encode("utf-32-le", "surrogatepass"), "<u4")
                    for plane, part in zip(out[k], np.array_split(codes, channels)):
                        if len(part) > 1:
                            cells = np.bincount((part[:-1] % h * w + part[1:] % w).astype(np.int64), minlength=w * h)
                            plane[:] = np.sqrt(cells / (len(part) - 1))
                px = pa.ListArray.from_arrays(pa.array(np.arange(n + 1) * size, pa.int32()), pa.array(out.ravel()))
                yield pa.RecordBatch.from_arrays([batch.column("id"), batch.column("label"), *(pa.array(np.full(n, x), pa.int32()) for x in (w, h, channels)), px], ["id", "label", "w", "h", "ch", "px"])

    return docs.select(F.col("doc_id").alias("id"), F.col(label).cast("string").alias("label"), "text").mapInArrow(run, IMAGE)


def embedding_images(embeddings: DataFrame) -> DataFrame:
    """FX2: each vector as an 8 by 8 image."""
    return embeddings.select(F.col("vec_id").alias("id"), F.col("label").cast("string").alias("label"), F.lit(8).alias("w"), F.lit(8).alias("h"), F.lit(1).alias("ch"), F.col("embedding").alias("px"))


def planted_faces(embeddings: DataFrame, strength: float = 0.8) -> DataFrame:
    """FX3: each vector plus a unit prototype of its label, so that the label shows."""
    from ..functions import keyed_uniform

    raw = F.transform(F.sequence(F.lit(0), F.lit(63)), lambda i: 2.0 * keyed_uniform("proto", F.col("label").cast("string"), i.cast("string")) - 1.0)
    # the prototype and its length are bound as lambda variables: as columns they would be worked out again for each entry
    moved = lambda proto, norm: F.zip_with("embedding", proto, lambda x, p: (x + strength * (p / norm)).cast("float"))
    length = lambda proto: F.sqrt(F.aggregate(proto, F.lit(0.0), lambda a, x: a + x * x))
    px = F.transform(F.array(raw), lambda proto: F.transform(F.array(length(proto)), lambda norm: moved(proto, norm)))[0][0]
    return embeddings.select(F.col("vec_id").alias("id"), F.col("label").cast("string").alias("label"), F.lit(8).alias("w"), F.lit(8).alias("h"), F.lit(1).alias("ch"), px.alias("px"))


def text_raster(docs: DataFrame, label: str = "lang", chars: int | None = None, cells: int = 1 << 20) -> DataFrame:
    """FX6: lines of text as rows, character codes as values; short lines are filled with zeros.

    A raster has lines times the longest line, which can be far more than the text: about
    ``cells`` values, or one raster, are held at a time.
    """

    def made(rows: list[tuple]) -> pa.RecordBatch:
        ids, names, ws, hs, px = zip(*rows)
        ends = np.cumsum([0, *map(len, px)])
        values = pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(np.concatenate(px)))
        columns = [pa.array(ids, pa.int64()), pa.array(names, pa.string()), pa.array(ws, pa.int32()), pa.array(hs, pa.int32()), pa.array([1] * len(ids), pa.int32()), values]
        return pa.RecordBatch.from_arrays(columns, ["id", "label", "w", "h", "ch", "px"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows, size = [], 0
        for whole in batches:
            for at in range(0, whole.num_rows, 64):
                batch = whole.slice(at, 64)
                for i, name, text in zip(*(batch.column(x).to_pylist() for x in ("id", "label", "text"))):
                    lines = (text or "")[:chars].split("\n")
                    w = max(1, max(map(len, lines)))
                    if rows and size + w * len(lines) > cells:
                        yield made(rows)
                        rows, size = [], 0
                    grid = np.zeros((len(lines), w), np.float32)
                    for k, line in enumerate(lines):
                        grid[k, : len(line)] = np.frombuffer(line.encode("utf-32-le", "surrogatepass"), "<u4")
                    rows.append((i, name, w, len(lines), grid.ravel()))
                    size += grid.size
        if rows:
            yield made(rows)

    return docs.select(F.col("doc_id").alias("id"), F.col(label).cast("string").alias("label"), "text").mapInArrow(run, IMAGE)


def text_sides(docs: DataFrame) -> DataFrame:
    """The sides of each text's raster without making it: id, w, h."""
    lines = F.split(F.coalesce("text", F.lit("")), "\n", -1)
    return docs.select(F.col("doc_id").alias("id"), F.greatest(F.lit(1), F.array_max(F.transform(lines, F.length))).alias("w"), F.size(lines).alias("h"))


def fact_grid(lineitem: DataFrame) -> DataFrame:
    """FX4: per supplier the counts of items by ship week (53) and quantity (50), flattened."""
    cell = (F.weekofyear("l_shipdate") - 1) * 50 + F.least(F.lit(50), F.greatest(F.lit(1), F.col("l_quantity").cast("int"))) - 1
    counts = lineitem.where(cell.isNotNull()).groupBy(F.col("l_suppkey").cast("long").alias("l_suppkey"), cell.alias("cell")).count()
    cells = counts.groupBy("l_suppkey").agg(F.collect_list("cell").alias("at"), F.collect_list("count").alias("n"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        size = 53 * 50
        for whole in batches:
            for start in range(0, whole.num_rows, 1024):
                batch = whole.slice(start, 1024)
                rows, at = batch.num_rows, batch.column("at")
                owner = np.repeat(np.arange(rows), np.asarray(at.value_lengths()))
                grid = np.zeros((rows, size), np.float32)
                grid[owner, np.asarray(at.flatten())] = np.asarray(batch.column("n").flatten())
                px = pa.ListArray.from_arrays(pa.array(np.arange(rows + 1) * size, pa.int32()), pa.array(grid.ravel()))
                yield pa.RecordBatch.from_arrays([batch.column("id"), px], ["id", "px"])

    grids = cells.select(F.col("l_suppkey").alias("id"), "at", "n").mapInArrow(run, "id long, px array<float>")
    return grids.select("id", F.lit(None).cast("string").alias("label"), F.lit(50).alias("w"), F.lit(53).alias("h"), F.lit(1).alias("ch"), "px")


def event_windows(events: DataFrame) -> DataFrame:
    """FX5: per user and day the counts by hour (24) and event type (5), flattened."""
    kinds = F.pmod(F.crc32("event_type"), F.lit(5)).cast("int")
    counts = events.groupBy("user_id", F.to_date("ts").alias("day"), (F.hour("ts") * 5 + kinds).alias("cell")).count()
    maps = counts.groupBy("user_id", "day").agg(F.map_from_entries(F.collect_list(F.struct("cell", "count"))).alias("m"))
    return maps.select("user_id", "day", F.transform(F.sequence(F.lit(0), F.lit(119)), lambda i: F.coalesce(F.try_element_at("m", i), F.lit(0)).cast("float")).alias("px"))


def parse_pnm(raw: bytes) -> tuple[int, int, int, np.ndarray]:
    """(width, height, channels, values) of a binary or plain grey or colour bitmap."""
    fields, at = [], 0
    while len(fields) < 4:
        while raw[at : at + 1].isspace():
            at += 1
        if raw[at : at + 1] == b"#":
            at = raw.index(b"\n", at)
            continue
        end = at
        while end < len(raw) and not raw[end : end + 1].isspace():
            end += 1
        fields.append(raw[at:end])
        at = end
    kind, w, h, top = fields[0], *map(int, fields[1:])
    channels = 3 if kind in (b"P3", b"P6") else 1
    if kind in (b"P5", b"P6"):
        values = np.frombuffer(raw, ">u2" if top > 255 else np.uint8, w * h * channels, at + 1)
    elif kind in (b"P2", b"P3"):
        values = np.array(raw[at:].split(), np.int64)[: w * h * channels]
    else:
        raise ValueError("not a grey or colour bitmap")
    planes = values.reshape(h, w, channels).transpose(2, 0, 1)
    return w, h, channels, planes.astype(np.float32).ravel()


def images(spark: SparkSession, path: str, glob: str = "*.p[gp]m") -> DataFrame:
    """A folder of bitmaps; the person is the name of the file's folder, the id a hash of its path."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for i, name, raw in zip(*(batch.column(x).to_pylist() for x in ("id", "label", "content"))):
                w, h, ch, px = parse_pnm(raw)
                rows.append({"id": i, "label": name, "w": w, "h": h, "ch": ch, "px": px.tolist()})
            yield pa.RecordBatch.from_pylist(rows, schema=pa.schema([("id", pa.int64()), ("label", pa.string()), ("w", pa.int32()), ("h", pa.int32()), ("ch", pa.int32()), ("px", pa.list_(pa.float32()))]))

    files = spark.read.format("binaryFile").option("pathGlobFilter", glob).option("recursiveFileLookup", "true").load(path)
    return files.select(F.xxhash64("path").alias("id"), F.element_at(F.split("path", "/"), -2).alias("label"), "content").mapInArrow(run, IMAGE)


class FaceGridSource(DataSource):
    """``spark.read.format("facegrid")``: deterministic test images, one partition per block of ids."""

    @classmethod
    def name(cls) -> str:
        return "facegrid"

    def schema(self) -> str:
        return IMAGE

    def reader(self, schema) -> DataSourceReader:
        return _FaceGridReader({k: int(v) for k, v in self.options.items()})


class _FaceGridReader(DataSourceReader):
    def __init__(self, options: dict[str, int]):
        self.options = options

    def partitions(self) -> list[InputPartition]:
        rows, size = self.options.get("rows", 100), self.options.get("block", 50)
        return [InputPartition((at, min(rows, at + size))) for at in range(0, rows, size)]

    def read(self, partition: InputPartition):
        persons, w, h = (self.options.get(k, v) for k, v in (("persons", 5), ("w", 8), ("h", 8)))
        for i in range(*partition.value):
            rng = np.random.default_rng(i)
            face = np.random.default_rng(10_000 + i % persons).random(w * h)
            yield i, f"p{i % persons}", w, h, 1, (face + 0.2 * rng.random(w * h)).astype(np.float32).tolist()
