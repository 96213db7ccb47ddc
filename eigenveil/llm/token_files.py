"""Token-id shards compressed document by document with one trained zstandard dictionary.

A corpus folder holds ``dictionary`` (one Parquet row: hash, dictionary, id width),
``shards``: raw files of one block each, and ``index``: one Parquet row per block with its
file, place in the order, counts and first and last doc_id.  A block is

* 72 bytes of header (little-endian): magic, dictionary hash, shard, number within the
  shard, documents, tokens, bytes of all frames (u64), first and last doc_id (i64);
* for each document its doc_id (i64, null as the lowest value), the end of its frame
  (u64) and its number of tokens (u64): three arrays, the offset index;
* the frames, each a zstandard frame of one document's ids under the shared dictionary;
* one line end, which the writer adds.

A block holds ``block_docs`` documents and, but for its last document, ``block_bytes``
bytes at most, so no file grows with long documents.  One document is read with its
index entries, the files they name and its own frame, however short it is.
Documents lie in ascending doc_id order through all blocks.  Null texts are empty
documents, a null doc_id comes first, documents with equal ids keep no stated order
among themselves, further columns are ignored, an empty table gives a folder that
reads back as no rows.  With 16-bit ids an id of 65,536 or more raises a ValueError.
"""

from __future__ import annotations

import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
import zstandard
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import bounded_sample, new_path, per_worker, tidy_shuffles, trim
from .tokens import encoder, in_chunks

MAGIC = b"ZIDS\x02\x00\x00\x00"
HEADER = "<8sQQQQQQqq"
HEADER_BYTES = struct.calcsize(HEADER)
_LOWEST = -(1 << 63)
_SHARDS = "shard long, block long, doc_id long, place long, local_start long, n_tokens long, n_bytes long, ids_crc32 long"
_INDEX = ["shard", "block", "docs", "tokens", "bytes", "first_id", "last_id"]
#: Bytes of one sample of the dictionary's training.
_SAMPLE = 8192


def _packed(ids: bytes, end_id: int | None, narrow: bool) -> tuple[bytes, int]:
    got = np.frombuffer(ids, np.uint32)
    if end_id is not None:
        got = np.append(got, np.uint32(end_id))
    if narrow and len(got) and got.max() > 0xFFFF:
        raise ValueError("an id does not fit 16 bits: write with narrow=False")
    return got.astype(np.uint16 if narrow else np.uint32).tobytes(), len(got)


def _samples(ids: bytes, pieces: int) -> list[bytes]:
    """At most ``pieces`` samples of ``_SAMPLE`` bytes, spread evenly over the serialised ids."""
    cuts = -(-len(ids) // _SAMPLE)
    chosen = range(cuts) if cuts <= pieces else sorted({k * cuts // pieces for k in range(pieces)})
    return [ids[k * _SAMPLE : (k + 1) * _SAMPLE] for k in chosen]


def train_dictionary(docs: DataFrame, vocabulary: str, narrow: bool, sample_docs: int, sample_pieces: int, dictionary_bytes: int, end_id: int | None) -> bytes:
    """Train on samples of the serialised ids of at most 5/4 of ``sample_docs`` documents; b"" if too few."""

    def serialised(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for start, texts in in_chunks(batch.column("text")):
                got = [s for x in encoder(vocabulary).encode(texts) for s in _samples(_packed(x, end_id, narrow)[0], sample_pieces)]
                yield pa.RecordBatch.from_pydict({"ids": pa.array(got, pa.binary())})

    chosen = bounded_sample(docs.select("doc_id", "text"), "doc_id", sample_docs).mapInArrow(serialised, "ids binary")
    samples = [bytes(x.ids) for x in chosen.collect()]
    try:
        return zstandard.train_dictionary(dictionary_bytes, samples).as_bytes()
    except (zstandard.ZstdError, ValueError):
        return b""


def _compressor(raw: bytes, level: int) -> zstandard.ZstdCompressor:
    return zstandard.ZstdCompressor(level=level, dict_data=zstandard.ZstdCompressionDict(raw) if raw else None, write_content_size=True, write_dict_id=False)


def _decompressor(raw: bytes) -> zstandard.ZstdDecompressor:
    return zstandard.ZstdDecompressor(dict_data=zstandard.ZstdCompressionDict(raw) if raw else None)


def shard_edges(docs: DataFrame, rows: int, shard_docs: int) -> np.ndarray:
    """The last doc_id of each shard but the last: Spark's own range sampler over the ids alone."""
    shards = -(-rows // shard_docs)
    if shards < 2:
        return np.empty(0, np.int64)
    dealt = docs.select("doc_id").where("doc_id IS NOT NULL").repartitionByRange(shards, "doc_id")
    ends = dealt.groupBy(F.spark_partition_id().alias("p")).agg(F.max("doc_id").alias("end")).orderBy("end").collect()
    return np.array([r["end"] for r in ends][:-1], np.int64)


def write_shards(docs: DataFrame, path: str, vocabulary: str, *, end_id: int | None = 2, block_docs: int = 16_384, block_bytes: int = 32 << 20, sample_docs: int = 1_000, sample_pieces: int = 4, dictionary_bytes: int = 65_536, level: int = 3, narrow: bool = True) -> None:
    """Encode ``docs(doc_id, text)`` and write them under ``path``, which must not exist.

    ``narrow`` stores 16-bit ids.  The dictionary is fitted on a bounded sample of about
    ``sample_docs`` documents, ``sample_pieces`` pieces of 8,192 bytes of each at most;
    every document is encoded with it.
    """
    spark = docs.sparkSession
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    raw = train_dictionary(docs, vocabulary, narrow, sample_docs, sample_pieces, dictionary_bytes, end_id)
    mark = xxhash.xxh3_64_intdigest(raw)
    head = pa.Table.from_pydict({"hash": [struct.unpack("<q", struct.pack("<Q", mark))[0]], "dictionary": [raw], "width": [2 if narrow else 4]})
    spark.createDataFrame(head).coalesce(1).write.parquet(f"{path}/dictionary")
    edges = shard_edges(docs, docs.count(), block_docs)

    def frames(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pack = per_worker(("zstd", mark, level), lambda: _compressor(raw, level)).compress
        for batch in batches:
            for start, texts in in_chunks(batch.column("text")):
                got = [_packed(x, end_id, narrow) for x in encoder(vocabulary).encode(texts)]
                ids = batch.column("doc_id").slice(start, len(got))
                shard = np.searchsorted(edges, np.asarray(ids.fill_null(_LOWEST)), "left")
                yield pa.RecordBatch.from_pydict({"shard": pa.array(shard, pa.int32()), "doc_id": ids, "n_tokens": pa.array([n for _, n in got], pa.int64()), "frame": pa.array([pack(x) for x, _ in got], pa.binary())})
                del got
        trim()

    def blocks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shard, number, ids, tokens, held, size = None, 0, [], [], [], 0

        def block() -> pa.RecordBatch:
            ends = np.cumsum([len(x) for x in held], dtype="<u8")
            header = struct.pack(HEADER, MAGIC, mark, shard, number, len(held), sum(tokens), int(ends[-1]), ids[0], ids[-1])
            body = b"".join([header, np.array(ids, "<i8").tobytes(), ends.tobytes(), np.array(tokens, "<u8").tobytes(), *held])
            held.clear()  # one copy of a block at a time
            return pa.RecordBatch.from_pydict({"block": pa.array([body], pa.binary())})

        for row in (row for batch in batches for at in range(0, batch.num_rows, 1000) for row in zip(*(batch.column(x).slice(at, 1000).to_pylist() for x in ("shard", "doc_id", "n_tokens", "frame")))):
            if held and (row[0] != shard or len(held) >= block_docs or size >= block_bytes):
                yield block()
                number = number + 1 if row[0] == shard else 0
                ids, tokens, held, size = [], [], [], 0
            shard = row[0]
            ids.append(_LOWEST if row[1] is None else row[1])
            tokens.append(row[2])
            held.append(row[3])
            size += len(row[3])
        if held:
            yield block()
        trim()

    encoded = docs.mapInArrow(frames, "shard int, doc_id long, n_tokens long, frame binary")
    ordered = encoded.repartitionById(len(edges) + 1, F.col("shard")).sortWithinPartitions("shard", "doc_id", F.xxhash64("frame"))
    with tidy_shuffles(spark):
        ordered.mapInArrow(blocks, "block binary").select(F.col("block").cast("string").alias("value")).write.option("maxRecordsPerFile", 1).text(f"{path}/shards")

    def headers(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            heads = [struct.unpack(HEADER, x)[2:] for x in batch.column("head").to_pylist() if len(x) == HEADER_BYTES]
            columns = list(zip(*heads)) or [()] * len(_INDEX)
            paths = [p for p, x in zip(batch.column("path").to_pylist(), batch.column("head").to_pylist()) if len(x) == HEADER_BYTES]
            yield pa.RecordBatch.from_arrays([pa.array(paths, pa.string()), *(pa.array(c, pa.int64()) for c in columns)], ["path", *_INDEX])

    files = spark.read.format("binaryFile").load(f"{path}/shards").select("path", F.substring("content", 1, HEADER_BYTES).alias("head"))
    files.mapInArrow(headers, "path string, " + ", ".join(f"{x} long" for x in _INDEX)).write.parquet(f"{path}/index")


def _open(content: memoryview) -> tuple:
    """(dictionary hash, shard, block, doc_ids, frame ends, tokens, frames) of a block."""
    magic, mark, shard, number, docs, _, size, _, _ = struct.unpack_from(HEADER, content)
    if magic != MAGIC:
        raise ValueError("not a block of token ids")
    arrays = [np.frombuffer(content, kind, docs, HEADER_BYTES + 8 * docs * i) for i, kind in enumerate(("<i8", "<u8", "<u8"))]
    at = HEADER_BYTES + 24 * docs
    return mark, shard, number, *arrays, content[at : at + size]


def _dictionary(spark: SparkSession, path: str) -> tuple[int, bytes, int]:
    row = spark.read.parquet(f"{path}/dictionary").first()
    return row["hash"] & ((1 << 64) - 1), bytes(row["dictionary"]), row["width"]


def _starts(index: DataFrame, run: int = 1024) -> DataFrame:
    """(shard, block, base): the tokens before each block, by sums within runs of shards and over the runs."""
    placed = index.select("shard", "block", "tokens", F.floor(F.col("shard") / run).alias("run"))
    inner = Window.partitionBy("run").orderBy("shard", "block").rowsBetween(Window.unboundedPreceding, -1)
    runs = placed.groupBy("run").agg(F.sum("tokens").alias("all"))
    outer = Window.orderBy("run").rowsBetween(Window.unboundedPreceding, -1)
    before = runs.select("run", F.coalesce(F.sum("all").over(outer), F.lit(0)).alias("before"))
    within = placed.withColumn("within", F.coalesce(F.sum("tokens").over(inner), F.lit(0)))
    return within.join(before, "run").select("shard", "block", (F.col("before") + F.col("within")).alias("base"))


def read_shards(spark: SparkSession, path: str) -> DataFrame:
    """One row per document: doc_id, start (ids before it), n_tokens, n_bytes, ids_crc32, shard, block, place."""
    mark, raw, width = _dictionary(spark, path)

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        unpack = per_worker(("unzstd", mark), lambda: _decompressor(raw)).decompress
        for batch in batches:
            for content in batch.column("content"):
                content = content.as_buffer()  # the batch's own memory
                if not content or not content.size:
                    continue
                seen, shard, number, ids, ends, tokens, body = _open(memoryview(content))
                if seen != mark:
                    raise ValueError("the block was written with another dictionary")
                starts = np.concatenate([[0], ends[:-1]]).astype(np.int64)
                crc = []
                for s, e, n in zip(starts.tolist(), ends.tolist(), tokens.tolist()):
                    got = np.frombuffer(unpack(body[s:e]) if e > s else b"", np.uint16 if width == 2 else np.uint32)
                    if len(got) != n:
                        raise ValueError("a frame does not hold the tokens that its index names")
                    crc.append(zlib.crc32(got.astype("<u4").tobytes()))
                same = lambda x: pa.array(np.full(len(ids), x), pa.int64())
                columns = [same(shard), same(number), pa.array(ids, pa.int64(), mask=ids == _LOWEST), pa.array(np.arange(len(ids)), pa.int64()), pa.array((np.cumsum(tokens) - tokens).astype(np.int64))]
                columns += [pa.array(tokens.astype(np.int64)), pa.array(ends.astype(np.int64) - starts), pa.array(crc, pa.int64())]
                yield pa.RecordBatch.from_arrays(columns, [x.split()[0] for x in _SHARDS.split(", ")])
        trim()

    docs = spark.read.format("binaryFile").load(f"{path}/shards").select("content").mapInArrow(rows, _SHARDS)
    placed = docs.join(_starts(spark.read.parquet(f"{path}/index")), ["shard", "block"])
    return placed.select("doc_id", (F.col("base") + F.col("local_start")).alias("start"), "n_tokens", "ids_crc32", "n_bytes", "shard", "block", "place")


def read_document(spark: SparkSession, path: str, doc_id: int) -> list[list[int]]:
    """The ids of the documents with this id (more than one if the id repeats), from the files that the index names."""
    mark, raw, width = _dictionary(spark, path)
    files = [r["path"] for r in spark.read.parquet(f"{path}/index").where((F.col("first_id") <= doc_id) & (F.col("last_id") >= doc_id)).select("path").collect()]
    if not files:
        return []

    def find(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for content in batch.column("content").to_pylist():
                _, _, _, ids, ends, _, body = _open(memoryview(content))
                for i in range(*np.searchsorted(ids, [doc_id, doc_id + 1]).tolist()):
                    frame = body[int(ends[i - 1]) if i else 0 : int(ends[i])]
                    got = np.frombuffer(_decompressor(raw).decompress(frame), np.uint16 if width == 2 else np.uint32)
                    yield pa.RecordBatch.from_pydict({"ids": pa.array([got.tolist()], pa.list_(pa.int64()))})

    content = spark.read.format("binaryFile").load(files).select("content")
    return [list(x.ids) for x in content.mapInArrow(find, "ids array<long>").collect()]


def token_files(docs: DataFrame, vocabulary: str, path: str | None = None, **options) -> DataFrame:
    """Write ``docs`` as shards (to a new shared folder by default) and read every document back."""
    path = path or new_path(docs.sparkSession, "token-shards")
    write_shards(docs, path, vocabulary, **options)
    return read_shards(docs.sparkSession, path)
