"""Near-duplicate documents by MinHash bands, odd sketches and a check on full sets.

Texts are lower-cased (A-Z) and cut at ASCII white space; the set of a document is its
distinct 5-word shingles (a shorter text is one shingle, a text without words has none).

1. One pass gives each document the size and a 128-bit fingerprint of its set, ``BANDS``
   band keys of ``ROWS`` MinHash values and an odd sketch: a bitmap in which every
   MinHash sample flips the bit it is hashed to, so that samples two sets share cancel.
   The set bits of the XOR of two sketches estimate the similarity (``similarity``).
2. Documents with equal fingerprints are one class, named by its smallest doc_id.
3. In each band, classes with one key are joined to one of them, the pivot.  Pairs that
   the sketches hold possible are checked on full sets; links give components.  The same
   is done ``PIVOT_ROUNDS`` times, with pivots that nothing is linked to yet first, while
   a key has classes of more than one component, and only between components.
4. Classes that then share a band key but not yet a component meet in blocks of at most
   ``BLOCK`` rows, block pair by block pair: sketches and parity bitmaps are compared
   there, only pairs that they hold possible leave, and these are checked on full sets.
   So no link is lost to the choice of pivots, and no key lands in one task.

Joins on band keys and on pivots are sort-merge joins with an exchange on both sides,
which adaptive execution splits where a key is hot.

A pair at the threshold shares no band with probability (1 - 0.75**ROWS)**BANDS, about
5e-6.  The sketches' limit is the count of bits whose estimate lies four deviations under
the threshold, so fewer than one in 10,000 true pairs fails it.  A second parity bitmap,
of the full set instead of samples, rejects without error: two sets differ in at least as
many elements as their bitmaps differ in bits, and may differ in at most (100 - percent) /
(100 + percent) of their sizes' sum.

Null texts and texts without words have size 0 and are linked with nothing.  Rows that
share a doc_id are one document: the one with the most shingles (then the greatest
fingerprint) stands for it, and all get its component.  Rows without doc_id are linked
with nothing.  Further columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import WordHashes, byte_texts, materialise, mixed, sorted_groups, trim, window_hashes
from .components import connected_components

WIDTH = 5
BANDS, ROWS = 32, 4
SKETCH_WORDS = 8  # 512 bits
PARITY_WORDS = 32  # 2048 bits
PIVOT_ROUNDS, BLOCK = 2, 1024


def similarity(apart, samples: int = BANDS * ROWS, bits: int = 64 * SKETCH_WORDS):
    """The similarity that ``apart`` differing bits of two odd sketches estimate, at least 0.

    ``samples`` unshared with probability 1 - J flip ``2 * samples * (1 - J)`` bits in all,
    of which hits of even number cancel: the mean is bits / 2 * (1 - (1 - 2 / bits) ** flips).
    """
    share = np.minimum(np.asarray(apart, np.float64) * 2 / bits, 1 - 1e-9)
    return np.maximum(0.0, 1.0 - np.log1p(-share) / (2 * samples * np.log1p(-2 / bits)))


def sketch_limit(percent: int, samples: int = BANDS * ROWS, bits: int = 64 * SKETCH_WORDS, deviations: float = 4.0) -> int:
    """The most bits in which the sketches of sets at the threshold differ, up to ``deviations``.

    Shared samples vary as a binomial, and so do the bits that unshared ones set.
    """
    j = percent / 100
    spread = np.sqrt(j * (1 - j) / samples + ((1 - j) / (2 * samples)))
    lowest = max(0.0, j - deviations * spread)
    apart = np.arange(bits // 2)
    return int(apart[similarity(apart, samples, bits) >= lowest].max(initial=0))


def shingles(words: list[bytes], hashes: WordHashes, width: int = WIDTH) -> np.ndarray:
    """Distinct 64-bit shingle hashes, sorted."""
    if not words:
        return np.empty(0, np.uint64)
    got = hashes.of(words)
    return np.unique(window_hashes(got, min(width, len(words))) ^ np.uint64(min(width, len(words))))


class Signatures:
    def __init__(self, bands: int = BANDS, rows: int = ROWS, seed: int = 11):
        rng = np.random.default_rng(seed)
        k = bands * rows
        self.bands, self.rows = bands, rows
        self.a = rng.integers(1, 1 << 63, k, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
        self.b = rng.integers(0, 1 << 63, k, dtype=np.uint64)
        self.salt = mixed(np.arange(1, k + 1, dtype=np.uint64))

    def minima(self, items: np.ndarray) -> np.ndarray:
        """For each hash function the smallest 32-bit value (its upper half of a*x+b)."""
        out = np.full(len(self.a), 0xFFFFFFFF, np.uint32)
        for at in range(0, len(items), 1024):
            part = items[at : at + 1024]
            values = (part[None, :] * self.a[:, None] + self.b[:, None]) >> np.uint64(32)
            np.minimum(out, values.astype(np.uint32).min(1), out=out)
        return out

    def band_keys(self, minima: np.ndarray) -> np.ndarray:
        key = np.zeros(self.bands, np.uint64)
        for column in minima.reshape(self.bands, self.rows).T:
            key = mixed(key ^ column.astype(np.uint64)) + np.uint64(0x9E3779B97F4A7C15)
        return mixed(key + self.salt[: self.bands])

    def sketch(self, minima: np.ndarray) -> np.ndarray:
        """Parity bitmap: each (function, value) sample flips one bit."""
        place = mixed(minima.astype(np.uint64) + self.salt) % np.uint64(64 * SKETCH_WORDS)
        odd = (np.bincount(place.astype(np.int64), minlength=64 * SKETCH_WORDS) & 1).astype(np.uint8)
        return np.packbits(odd).view(np.uint64)


def parity(items: np.ndarray) -> np.ndarray:
    """Bitmap in which every element of the set flips one bit."""
    odd = (np.bincount((items % np.uint64(64 * PARITY_WORDS)).astype(np.int64), minlength=64 * PARITY_WORDS) & 1).astype(np.uint8)
    return np.packbits(odd).view(np.uint64)


def fingerprint(items: np.ndarray) -> tuple[int, int]:
    with np.errstate(over="ignore"):
        return int(mixed(items).sum(dtype=np.uint64).view(np.int64)), int(mixed(items + np.uint64(0x632BE59BD9B4E019)).sum(dtype=np.uint64).view(np.int64))


def sign_documents(docs: DataFrame, width: int = WIDTH) -> DataFrame:
    """doc_id, n_shingles, f0, f1, bands, sketch and parity (arrays of long; empty arrays for an empty set)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes, signer = WordHashes(), Signatures()
        for batch in batches:
            columns: list[list] = [[] for _ in range(6)]
            for text in byte_texts(batch.column("text")):
                items = shingles((text or b"").lower().split(), hashes, width)
                if len(items):
                    minima = signer.minima(items)
                    row = (len(items), *fingerprint(items), signer.band_keys(minima).view(np.int64), signer.sketch(minima).view(np.int64), parity(items).view(np.int64))
                else:
                    row = (0, 0, 0, [], [], [])
                for column, value in zip(columns, row):
                    column.append(value)
            lists = pa.list_(pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), *(pa.array(x, pa.int64()) for x in columns[:3]), *(pa.array(x, lists) for x in columns[3:])], ["doc_id", "n_shingles", "f0", "f1", "bands", "sketch", "parity"])
        del hashes
        trim()

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, n_shingles long, f0 long, f1 long, bands array<long>, sketch array<long>, parity array<long>")


def shingle_sets(docs: DataFrame, width: int = WIDTH) -> DataFrame:
    """doc_id, items (the sorted distinct shingle hashes), f0 and f1."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes = WordHashes()
        for batch in batches:
            for at in range(0, batch.num_rows, 1_000):
                part = batch.slice(at, 1_000)
                sets = [shingles((x or b"").lower().split(), hashes, width) for x in byte_texts(part.column("text"))]
                prints = [fingerprint(x) for x in sets]
                items = pa.array([x.view(np.int64) for x in sets], pa.list_(pa.int64()))
                names = ["doc_id", "items", "f0", "f1"]
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), items, *(pa.array([x[k] for x in prints], pa.int64()) for k in (0, 1))], names)
        del hashes
        trim()

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, items array<long>, f0 long, f1 long")


def _bits(a: str, b: str, words: int):
    return sum((F.bit_count(F.col(a)[k].bitwiseXOR(F.col(b)[k])) for k in range(words)), F.lit(0))


def _possible(percent: int, limit: int):
    """What the sizes, the odd sketches and the full parity bitmaps leave possible."""
    sizes = F.lit(100) * F.least("na", "nb") >= F.lit(percent) * F.greatest("na", "nb")
    apart = F.lit(100 + percent) * _bits("pa", "pb", PARITY_WORDS) <= F.lit(100 - percent) * (F.col("na") + F.col("nb"))
    return sizes & (_bits("sa", "sb", SKETCH_WORDS) <= limit) & apart


def _met(left: DataFrame, right: DataFrame, on) -> DataFrame:
    """A sort-merge join: adaptive execution splits its hot keys, which it can't in a hash join."""
    return left.join(right.hint("merge"), on)


def confirmed(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """Of ``pairs(a, b)`` those with 100 * intersection >= percent * union, by full sets."""
    left = sets.select(F.col("doc_id").alias("a"), F.col("items").alias("x"))
    right = sets.select(F.col("doc_id").alias("b"), F.col("items").alias("y"))
    both = F.size(F.array_intersect("x", "y")).cast("long")
    union = F.size("x") + F.size("y") - both
    return _met(_met(pairs, right, "b"), left, "a").where(100 * both >= percent * union).select("a", "b")


def block_pairs(members: DataFrame, classes: DataFrame, percent: int, limit: int, block: int = BLOCK) -> DataFrame:
    """Pairs (a, b) of ``members(band, key, doc_id, c)`` of one key and of unlike components that may be links.

    A key's members are dealt to blocks by a hash of their id; each pair of blocks is one
    group of at most twice ``block`` rows or so, and is compared in numpy.
    """
    order = ["band", "key", "x", "y"]
    sizes = materialise(members.groupBy("band", "key").agg(F.ceil(F.count("*") / block).cast("int").alias("blocks")), "key-sizes")
    own = F.pmod(F.xxhash64(F.lit(5), "doc_id"), F.col("blocks")).cast("int")
    dealt = _met(members, sizes, ["band", "key"]).withColumn("own", own).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    met = dealt.select("band", "key", F.least("own", "other").alias("x"), F.greatest("own", "other").alias("y"), "own", "doc_id", "c")
    wide = _met(met, classes.select("doc_id", "n_shingles", "sketch", "parity"), "doc_id")
    sent = wide.repartition(*order).sortWithinPartitions(*order, "own", "doc_id")

    def compare(table: pa.Table) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """Pairs of one group: of its two blocks, or of its only block."""
        x, y = table.column("x")[0].as_py(), table.column("y")[0].as_py()
        ids, c, n, own = (np.asarray(table.column(k)) for k in ("doc_id", "c", "n_shingles", "own"))
        sketch, parities = (np.asarray(table.column(k).combine_chunks().flatten()).view(np.uint64).reshape(len(ids), -1) for k in ("sketch", "parity"))
        split = int((own == x).sum()) if x < y else 0
        columns = np.arange(split, len(ids))
        for k in range(split or len(ids)):
            there = columns if split else columns[k + 1 :]
            there = there[(c[there] != c[k]) & (100 * np.minimum(n[there], n[k]) >= percent * np.maximum(n[there], n[k]))]
            there = there[np.bitwise_count(sketch[there] ^ sketch[k]).sum(1) <= limit]
            apart = np.bitwise_count(parities[there] ^ parities[k]).sum(1, dtype=np.int64)
            there = there[(100 + percent) * apart <= (100 - percent) * (n[there] + n[k])]
            if len(there):
                yield np.minimum(ids[there], ids[k]), np.maximum(ids[there], ids[k])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table in sorted_groups(batches, order):
            for a, b in compare(table):
                yield pa.RecordBatch.from_pydict({"a": pa.array(a, pa.int64()), "b": pa.array(b, pa.int64())})

    return sent.mapInArrow(run, "a long, b long").distinct()


def near_duplicates(docs: DataFrame, percent: int = 75, width: int = WIDTH, limit: int | None = None, block: int = BLOCK) -> DataFrame:
    """doc_id, n_shingles, component_id and kept for every row of ``docs(doc_id, text)``."""
    limit = sketch_limit(percent) if limit is None else limit
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    signed = materialise(sign_documents(docs, width), "signed").withColumn("n", F.col("n_shingles"))
    filled = signed.where("n > 0 AND doc_id IS NOT NULL")
    prints = F.struct("n", "f0", "f1")
    repeated = materialise(filled.groupBy("doc_id").agg(F.count("*").alias("rows"), F.max(prints).alias("most")).where("rows > 1").select("doc_id", "most"), "repeated")
    again = not repeated.isEmpty()
    if again:  # all rows of a document go by the text that stands for it
        told = signed.join(repeated, "doc_id", "left")
        signed = told.select("doc_id", "n_shingles", *(F.coalesce(f"most.{x}", x).alias(x) for x in ("n", "f0", "f1")), "bands", "sketch", "parity", (F.col("most").isNull() | (F.col("most") == prints)).alias("own"))
        filled = signed.where("n_shingles > 0 AND doc_id IS NOT NULL AND own")
    # classes of equal sets, each named by its smallest id
    named = F.min_by(F.struct("doc_id", "bands", "sketch", "parity"), "doc_id").alias("r")
    classes = materialise(filled.groupBy("f0", "f1", "n").agg(named).select("f0", "f1", F.col("n").alias("n_shingles"), "r.*"), "classes")
    a_side, b_side = (classes.select(F.col("doc_id").alias(x), F.col("n_shingles").alias(f"n{x}"), F.col("sketch").alias(f"s{x}"), F.col("parity").alias(f"p{x}")) for x in "ab")
    bands = classes.select("doc_id", F.posexplode("bands").alias("band", "key"))
    shared = materialise(bands.groupBy("band", "key").agg(F.count("*").alias("n")).where("n > 1").select("band", "key"), "shared-keys")
    members = materialise(_met(bands, shared, ["band", "key"]).select("band", "key", "doc_id", F.col("doc_id").alias("c"), F.lit(False).alias("linked")), "members")
    sets = shingle_sets(docs.join(members.select("doc_id").distinct(), "doc_id", "left_semi"), width)
    if again:
        sets = sets.join(classes.select("doc_id", "f0", "f1"), ["doc_id", "f0", "f1"], "left_semi").dropDuplicates(["doc_id"])
    sets = materialise(sets.select("doc_id", "items"), "sets")
    links: DataFrame | None = None
    found = docs.sparkSession.createDataFrame([], "id long, component long")

    def link(pairs: DataFrame) -> None:
        """Check pairs on full sets and renew the components."""
        nonlocal links, found
        new = materialise(confirmed(pairs, sets, percent), "links")
        if not new.isEmpty():
            links = new if links is None else links.union(new)
            found = materialise(connected_components(links), "found")

    def unsettled() -> DataFrame:
        """Members of keys with classes of more than one component."""
        component = F.coalesce("component", "doc_id").alias("c")
        placed = members.drop("c", "linked").join(found.withColumnRenamed("id", "doc_id"), "doc_id", "left").select("band", "key", "doc_id", component, F.col("component").isNotNull().alias("linked"))
        keys = materialise(placed.groupBy("band", "key").agg(F.min("c").alias("lo"), F.max("c").alias("hi")).where("lo < hi").select("band", "key"), "mixed-keys")
        return materialise(_met(placed, keys, ["band", "key"]), "members")

    for k in range(PIVOT_ROUNDS):
        first = F.struct("linked", F.xxhash64(F.lit(k), "doc_id")) if k else F.col("doc_id")
        pivots = materialise(members.groupBy("band", "key").agg(F.min_by(F.struct("doc_id", "c"), first).alias("pivot")), "pivots")
        star = _met(members, pivots, ["band", "key"]).where("pivot.c <> c").select(F.least("doc_id", "pivot.doc_id").alias("a"), F.greatest("doc_id", "pivot.doc_id").alias("b")).distinct()
        link(_met(_met(star, b_side, "b"), a_side, "a").where(_possible(percent, limit)).select("a", "b"))
        members = unsettled()
        if members.isEmpty():
            break
    else:
        link(block_pairs(members, classes, percent, limit, block))

    # back to every row: row -> class -> component
    placed = classes.select("f0", "f1", F.col("n_shingles").alias("n"), F.col("doc_id").alias("class_id")).join(found.withColumnRenamed("id", "class_id"), "class_id", "left").select("f0", "f1", "n", F.coalesce("component", "class_id").alias("component"))
    rows = signed.select("doc_id", "n_shingles", "n", "f0", "f1").join(placed, ["f0", "f1", "n"], "left")
    component = F.when(F.col("doc_id").isNotNull(), F.coalesce("component", "doc_id")).alias("component_id")
    return rows.select("doc_id", "n_shingles", component).withColumn("kept", F.col("doc_id").eqNullSafe(F.col("component_id")))
