"""Near-duplicate vectors by iterative quantisation and multi-index Hamming tables.

Equal vectors are collapsed to one class each.  From the mean and second moments of all
classes (principal axes) and a bounded sample, several rotations are learnt by iterative
quantisation, each from its own random start: codes are the signs of the centred,
rotated vectors, and the rotation is solved anew (orthogonal Procrustes) until the codes
lie close to it.  Each rotation gives a balanced code, cut into substrings of ``bits``
bits, one hash table each.  Vectors that share a bucket of some table are compared by the
cosine of their original values in double precision.

The number of bits follows from the number of classes (about ``LOAD`` in a bucket).  The
number of tables follows from the sample: its vectors are paired with others at exactly
the threshold's cosine, turned towards random directions and towards each other, and
tables are added until ``recall`` of the pairs of either kind share a bucket.  Pairs over
the threshold are found more often.  Where that takes over ``MOST_TABLES`` tables, the
substrings are made shorter, so buckets grow and no pair is given up.

A pair is counted in the first table that both vectors share, so no list of pairs is
made or deduplicated; of the links of a bucket only a spanning forest leaves it.  Large
buckets are split into blocks by a hash of the id, and blocks meet pairwise, so no task
gets an unbounded group.

Null, zero and non-finite vectors link with nothing and are their own component, as are
vectors of another dimension than most.  Rows of one vec_id count as one vector (the
greatest of them, component by component, if they differ); a row without vec_id links
with nothing.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import bounded_sample, materialise
from .components import connected_components
from .topk import _rotation, common_dimension, matrix, second_moments, valid_vectors

LOAD, BLOCK, MOST_TABLES = 16, 1024, 128
#: Leading principal directions that a code is made of, at most.
DIRECTIONS = 256


def iterative_quantisation(sample: np.ndarray, seed: int, rounds: int = 20) -> np.ndarray:
    """A rotation that brings ``sample`` (rows by directions) close to the corners of a cube."""
    turn = np.linalg.qr(np.random.default_rng(seed).normal(size=(sample.shape[1], sample.shape[1])))[0]
    for _ in range(rounds):
        left, _, right = np.linalg.svd(np.where(sample @ turn >= 0, 1.0, -1.0).T @ sample)
        turn = (left @ right).T
    return turn


def pairs_at(sample: np.ndarray, cosine: float, seed: int = 5) -> list[np.ndarray]:
    """For each unit row another one at ``cosine``: turned at random, and towards another row."""
    rng = np.random.default_rng(seed)
    out = []
    for aim in (rng.normal(size=sample.shape), sample[rng.permutation(len(sample))] + 1e-3 * rng.normal(size=sample.shape)):
        aim = aim - (aim * sample).sum(1, keepdims=True) * sample
        aim /= np.maximum(np.linalg.norm(aim, axis=1, keepdims=True), 1e-12)
        out.append(cosine * sample + np.sqrt(1 - cosine * cosine) * aim)
    return out


def table_keys(x: np.ndarray, projections: np.ndarray, offset: np.ndarray, bits: int) -> np.ndarray:
    """(rows, tables) bucket numbers: substrings of the signs, as integers."""
    tables = projections.shape[1] // bits
    signs = (x @ projections[:, : tables * bits] >= offset[: tables * bits]).reshape(len(x), tables, bits)
    return (signs * (1 << np.arange(bits))).sum(2).astype(np.int32)


def learn_codes(sample: np.ndarray, mean: np.ndarray, moments: np.ndarray, count: int, cosine: float, recall: float) -> tuple[np.ndarray, np.ndarray, int]:
    """(projections, offsets, bits): one column and one offset for each bit of all tables.

    ``mean`` and ``moments`` (of the outer products, per vector) are of all vectors.
    """
    axes = _rotation(moments - np.outer(mean, mean))[:, :DIRECTIONS]
    centred = (sample - mean) @ axes
    turned = pairs_at(sample, cosine)
    columns: list[np.ndarray] = []

    def projections(n: int) -> np.ndarray:
        while sum(c.shape[1] for c in columns) < n:
            columns.append(axes @ iterative_quantisation(centred, len(columns)))
        return np.concatenate(columns, 1)[:, :n]

    bits = int(np.clip(np.ceil(np.log2(max(1, count) / LOAD)), 0, 30))
    while bits:
        missed = [np.ones(len(sample), bool) for _ in turned]
        for tables in range(1, MOST_TABLES + 1):
            all_ = projections(tables * bits)
            part = all_[:, -bits:]
            here = table_keys(sample, part, mean @ part, bits)[:, 0]
            for left, other in zip(missed, turned):
                left &= table_keys(other, part, mean @ part, bits)[:, 0] != here
            if all(left.mean() <= 1 - recall for left in missed):
                return all_, mean @ all_, bits
        bits = max(0, bits - 3)
    return np.zeros((len(mean), 1)), np.full(1, -1.0), 1  # one bucket for all


def coded(vectors: DataFrame, projections: np.ndarray, offset: np.ndarray, bits: int) -> DataFrame:
    """vec_id, unit, copies, keys: one bucket number for each table."""
    dimension, tables = projections.shape[0], projections.shape[1] // bits

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = matrix(batch.column("unit"), dimension)
            keys = table_keys(x, projections, offset, bits)
            lists = pa.ListArray.from_arrays(pa.array(np.arange(len(x) + 1) * tables, pa.int32()), pa.array(keys.ravel()))
            yield pa.RecordBatch.from_arrays([batch.column("vec_id"), batch.column("unit"), batch.column("copies"), lists], ["vec_id", "unit", "copies", "keys"])

    return vectors.select("vec_id", "unit", "copies").mapInArrow(run, "vec_id long, unit array<double>, copies long, keys array<int>")


def _forest(ids: np.ndarray, left: np.ndarray, right: np.ndarray) -> list[tuple[int, int]]:
    """Edges of a spanning forest over local link lists."""
    root = list(range(len(ids)))

    def find(i: int) -> int:
        while root[i] != i:
            root[i] = root[root[i]]
            i = root[i]
        return i

    out = []
    for a, b in zip(left.tolist(), right.tolist()):
        x, y = find(a), find(b)
        if x != y:
            root[max(x, y)] = min(x, y)
            out.append((int(ids[a]), int(ids[b])))
    return out


def _links(unit: np.ndarray, keys: np.ndarray, place: int, split: int, cosine: float) -> tuple[np.ndarray, np.ndarray]:
    """Pairs (p, q) at ``cosine`` or more that no earlier table has: of rows before and from ``split``,
    or all pairs p < q if ``split`` is 0."""
    columns = np.arange(split, len(unit))
    left, right = [], []
    for at in range(0, split or len(unit), 256):
        mine = np.arange(at, min(at + 256, split or len(unit)))
        near = unit[mine] @ unit[columns].T >= cosine
        if not split:
            near &= columns[None, :] > mine[:, None]
        a, b = np.nonzero(near)
        a, b = mine[a], columns[b]
        for k in range(0, len(a), 1 << 18):
            p, q = a[k : k + (1 << 18)], b[k : k + (1 << 18)]
            first = ~(keys[p, :place] == keys[q, :place]).any(1) if place else np.ones(len(p), bool)
            left.append(p[first])
            right.append(q[first])
    none = np.empty(0, np.int64)
    return np.concatenate(left or [none]), np.concatenate(right or [none])


def _comparer(cosine: float, dimension: int, tables: int):
    """Arrow function over rows sorted by block pair: (vec_id, itself, links) and forest edges (n = 0)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: pa.Table | None = None

        def work(table: pa.Table, last: bool) -> tuple[pa.RecordBatch | None, pa.Table | None]:
            group = np.stack([np.asarray(table.column(x)) for x in ("place", "key", "x", "y")])
            cuts = np.flatnonzero(np.append(True, (group[:, 1:] != group[:, :-1]).any(0)))
            edges = np.append(cuts[1:], table.num_rows)
            done = len(cuts) if last else len(cuts) - 1
            if not done:
                return None, table
            whole = table.slice(0, int(edges[done - 1])).combine_chunks()
            ids, own = np.asarray(whole.column("vec_id")), np.asarray(whole.column("own"))
            unit = matrix(whole.column("unit").combine_chunks(), dimension)
            keys = np.asarray(whole.column("keys").combine_chunks().flatten()).reshape(-1, tables)
            copies = np.asarray(whole.column("copies"))
            out: list[list[np.ndarray]] = [[], [], []]
            for a, b in zip(cuts[:done].tolist(), edges[:done].tolist()):
                if b - a < 2:
                    continue
                place, x, y = int(group[0, a]), int(group[2, a]), int(group[3, a])
                split = int((own[a:b] == x).sum()) if x < y else 0
                if x < y and not 0 < split < b - a:
                    continue
                p, q = _links(unit[a:b], keys[a:b], place, split, cosine)
                if not len(p):
                    continue
                here = copies[a:b]
                count = np.bincount(p, here[q], b - a).astype(np.int64) + np.bincount(q, here[p], b - a).astype(np.int64)
                linked = np.flatnonzero(count)
                tree = np.array(_forest(ids[a:b], p, q), np.int64).reshape(-1, 2)
                for column, values in zip(out, ((ids[a:b][linked], tree[:, 0]), (ids[a:b][linked], tree[:, 1]), (count[linked], np.zeros(len(tree), np.int64)))):
                    column.extend(values)
            made = pa.RecordBatch.from_arrays([pa.array(np.concatenate(x) if x else np.empty(0, np.int64), pa.int64()) for x in out], ["vec_id", "to", "n"])
            return made, None if last else table.slice(int(edges[done - 1]))

        for batch in batches:
            now = pa.Table.from_batches([batch])
            made, held = work(pa.concat_tables([held, now]) if held is not None else now, False)
            if made is not None:
                yield made
        if held is not None:
            yield work(held, True)[0]

    return run


def near_vectors(rows: DataFrame, cosine: float = 0.9, recall: float = 0.97, sample_rows: int = 4_000, block: int = BLOCK, column: str = "embedding") -> DataFrame:
    """vec_id, n_links, component_id and kept for every row of ``rows(vec_id, embedding)``."""
    rows = rows.select(F.col("vec_id").cast("long").alias("vec_id"), column)
    fine = valid_vectors(rows.where("vec_id IS NOT NULL"), column)
    dimension = common_dimension(fine, column)
    if not dimension:
        return rows.select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"), F.lit(True).alias("kept"))
    # scaled by the greatest component first, so that lengths neither overflow nor vanish
    top = F.array_max(F.transform(column, F.abs))
    fine = fine.where((F.size(column) == dimension) & (top > 0)).withColumn(column, F.transform(column, lambda x: x / top))
    length = F.sqrt(F.aggregate(column, F.lit(0.0), lambda a, x: a + x * x))
    vectors = fine.withColumn("length", length).select("vec_id", F.transform(column, lambda x: x / F.col("length") + 0.0).alias("unit"))
    vectors = materialise(vectors.groupBy("vec_id").agg(F.max("unit").alias("unit")).select("*", F.xxhash64("unit").alias("f0"), F.xxhash64(F.lit(7), "unit").alias("f1")), "units")
    classes = materialise(vectors.groupBy("f0", "f1").agg(F.min_by("unit", "vec_id").alias("unit"), F.min("vec_id").alias("vec_id"), F.count("*").alias("copies")), "unit-classes")
    count = classes.count()
    if not count:
        return rows.select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"), F.lit(True).alias("kept"))
    # the mean is the last row of the moments of the vectors with a one appended
    moments = second_moments(classes.select(F.concat("unit", F.array(F.lit(1.0))).alias("unit")), dimension + 1, "unit") / count
    chosen = bounded_sample(classes.select("vec_id", "unit"), "vec_id", sample_rows).orderBy("vec_id").collect()
    sample = np.array([r["unit"] for r in chosen]).reshape(-1, dimension)
    projections, offset, bits = learn_codes(sample, moments[-1, :-1], moments[:-1, :-1], count, cosine, recall)
    tables = projections.shape[1] // bits
    codes = materialise(coded(classes, projections, offset, bits), "codes")
    places = codes.select("vec_id", F.posexplode("keys").alias("place", "key"))
    full = materialise(places.groupBy("place", "key").count().where("count > 1").select("place", "key", F.ceil(F.col("count") / block).cast("int").alias("blocks")), "buckets")
    own = F.pmod(F.xxhash64("vec_id"), F.col("blocks")).cast("int")
    member = places.join(full.hint("merge"), ["place", "key"]).withColumn("own", own)
    # block pairs (x <= y) that this row takes part in
    met = member.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))).select("vec_id", "place", "key", F.least("own", "other").alias("x"), F.greatest("own", "other").alias("y"), "own")
    wide = met.join(codes, "vec_id")

    order = ["place", "key", "x", "y"]
    sent = wide.select(*order, "own", "vec_id", "unit", "copies", "keys").repartition(*order).sortWithinPartitions(*order, "own", "vec_id")
    found = materialise(sent.mapInArrow(_comparer(cosine, dimension, tables), "vec_id long, to long, n long"), "compared")
    counts = found.where("n > 0").groupBy("vec_id").agg(F.sum("n").alias("links"))
    component = connected_components(found.where("n = 0").select(F.col("vec_id").alias("a"), F.col("to").alias("b"))).withColumnRenamed("id", "vec_id")
    # vector -> class -> links of other classes, own copies and component
    named = classes.join(counts, "vec_id", "left").join(component, "vec_id", "left").select("f0", "f1", (F.coalesce("links", F.lit(0)) + F.col("copies") - 1).alias("n_links"), F.coalesce("component", "vec_id").alias("component"))
    each = vectors.select("vec_id", "f0", "f1").join(named.hint("merge"), ["f0", "f1"]).select("vec_id", "n_links", "component")
    done = rows.select("vec_id").join(each, "vec_id", "left")
    of = F.coalesce("component", "vec_id")
    return done.select("vec_id", F.coalesce("n_links", F.lit(0)).alias("n_links"), of.alias("component_id"), F.col("vec_id").eqNullSafe(of).alias("kept"))
