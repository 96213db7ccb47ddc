"""Exact top-k inner products of integer vectors, longest vectors first.

Components become floor(256 * x).  Candidates are packed into blocks in descending
order of length, so a block's first length bounds its scores.  All vectors are also
held in a rotated basis (singular directions of the second moments), in which the
leading coordinates carry most of the length: the partial product over them plus the
product of the two residual lengths (Cauchy-Schwarz) bounds the whole product.  A
candidate whose bound lies below the query's k-th best score so far is not computed;
all others are, in exact integers.

Queries and candidates are packed blocks of bounded size.  Candidate blocks form groups
and query blocks parts, whose numbers follow from the counts of rows; each part meets
each group in one task, which holds ``CHUNK`` blocks of either side at most, and the best
k of each group are merged.  Before that every query meets the block of the longest
candidates, and its k-th best score there is the floor from which every group starts.
One block (the longest) and the rotation go to all executors; nothing else is broadcast
by this module.

Vectors that are null, empty, of another dimension than most or that hold null or
non-finite components take no part.  Ties go to the smaller vec_id; equal vectors are
candidates like any others.  A query with fewer candidates gets all it has; an empty
table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import materialise

BLOCK, QUERY_BLOCK, CHUNK = 2048, 512, 32
#: Leading rotated coordinates of the partial product.
LEAD = 16


def valid_vectors(rows: DataFrame, column: str = "embedding") -> DataFrame:
    """Rows whose vector is not null and holds finite numbers only, as doubles."""
    vector = F.col(column).cast("array<double>")
    fine = F.col(column).isNotNull() & (F.size(column) > 0) & F.forall(vector, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < F.lit(float("inf"))))
    return rows.where(fine).withColumn(column, vector)


def common_dimension(rows: DataFrame, column: str = "embedding") -> int:
    """The most frequent length of the vectors (the greatest of equally frequent ones), 0 if there are none."""
    row = rows.groupBy(F.size(column).alias("d")).count().orderBy(F.desc("count"), F.desc("d")).first()
    return row["d"] if row else 0


def matrix(column: pa.Array, dimension: int) -> np.ndarray:
    """Doubles (rows, dimension) of a list column without nulls."""
    return np.asarray(column.flatten().cast(pa.float64())).reshape(-1, dimension)


def second_moments(rows: DataFrame, dimension: int, column: str) -> np.ndarray:
    """Sum of outer products over all rows: one partial of dimension squared per task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((dimension, dimension))
        for batch in batches:
            x = matrix(batch.column(0), dimension)
            total += x.T @ x
        yield pa.RecordBatch.from_pydict({"i": pa.array(np.repeat(np.arange(dimension), dimension)), "j": pa.array(np.tile(np.arange(dimension), dimension)), "v": pa.array(total.ravel())})

    got = rows.select(column).mapInArrow(run, "i long, j long, v double").groupBy("i", "j").agg(F.sum("v").alias("v")).collect()
    out = np.zeros((dimension, dimension))
    for r in got:
        out[r["i"], r["j"]] = r["v"]
    return out


def _rotation(moments: np.ndarray) -> np.ndarray:
    values, vectors = np.linalg.eigh((moments + moments.T) / 2)
    return vectors[:, np.argsort(-values)]


def _packed(rows: DataFrame, size: int, dimension: int, by: str) -> DataFrame:
    """Blocks of rows in the order of their partition: ids, quantised vectors, greatest length."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x, ids = matrix(batch.column("q"), dimension), np.asarray(batch.column("vec_id"))
            for at in range(0, len(ids), size):
                part = x[at : at + size]
                yield pa.RecordBatch.from_pydict({"ids": pa.array([ids[at : at + size].tobytes()], pa.binary()), "vectors": pa.array([part.tobytes()], pa.binary()), "longest": pa.array([float(np.sqrt((part * part).sum(1)).max())])})

    return rows.select("vec_id", "q").mapInArrow(run, "ids binary, vectors binary, longest double").withColumn(by, F.monotonically_increasing_id())


class _Best:
    """The k best (score, smaller id) of each query of one block."""

    def __init__(self, queries: int, k: int, least: np.ndarray | None = None):
        #: scores that k candidates of each query are known to reach
        self.least = np.full(queries, -np.iinfo(np.int64).max, np.int64) if least is None else least
        self.scores = np.full((queries, k), -np.iinfo(np.int64).max, np.int64)
        self.ids = np.full((queries, k), np.iinfo(np.int64).max, np.int64)

    def floor(self) -> np.ndarray:
        return np.maximum(self.scores[:, -1], self.least)

    def add(self, q: int, scores: np.ndarray, ids: np.ndarray) -> None:
        scores, ids = np.concatenate([self.scores[q], scores]), np.concatenate([self.ids[q], ids])
        order = np.lexsort((ids, -scores))[: self.scores.shape[1]]
        self.scores[q], self.ids[q] = scores[order], ids[order]


def _exact(queries: np.ndarray, candidates: np.ndarray) -> np.ndarray:
    """Integer products; doubles hold them exactly below 2**53, beyond it integers are used."""
    bound = float(np.abs(queries).max(initial=0)) * float(np.abs(candidates).max(initial=0)) * queries.shape[-1]
    if bound < 2**53:
        return (queries @ candidates.T).astype(np.int64)
    return queries.astype(np.int64) @ candidates.astype(np.int64).T


def search_block(best: _Best, query_ids: np.ndarray, queries: np.ndarray, ids: np.ndarray, vectors: np.ndarray, rotation: np.ndarray) -> int:
    """Offer a block of candidates to a block of queries; the number of products computed in full."""
    lengths = np.sqrt((vectors * vectors).sum(1))
    order = np.argsort(-lengths, kind="stable")
    ids, vectors, lengths = ids[order], vectors[order], lengths[order]
    turned, asked = vectors @ rotation, queries @ rotation
    lead = min(LEAD, vectors.shape[1])
    rest = np.sqrt(np.maximum((turned[:, lead:] ** 2).sum(1), 0))
    rest_q = np.sqrt(np.maximum((asked[:, lead:] ** 2).sum(1), 0))
    size_q = np.sqrt((queries * queries).sum(1))
    done = 0
    for at in range(0, len(ids), 256):
        part = slice(at, at + 256)
        floor = best.floor().astype(np.float64)
        slack = 1e-9 * size_q * lengths[at] + 1e-6
        live = np.flatnonzero(size_q * lengths[at] + slack >= floor)
        if not len(live):
            break
        bound = asked[live, :lead] @ turned[part, :lead].T + rest_q[live, None] * rest[None, part] + slack[live, None]
        open_ = bound >= floor[live, None]
        columns = np.flatnonzero(open_.any(0))
        rows = np.flatnonzero(open_.any(1))
        if not len(rows):
            continue
        products = _exact(queries[live[rows]], vectors[part][columns])
        done += products.size
        there = ids[part][columns]
        for r, q in enumerate(live[rows].tolist()):
            chosen = (products[r] >= best.scores[q, -1]) & (there != query_ids[q])
            if chosen.any():
                best.add(q, products[r][chosen], there[chosen])
    return done


def _block(row: dict) -> tuple[np.ndarray, np.ndarray]:
    ids = np.frombuffer(row["ids"], np.int64)
    return ids, np.frombuffer(row["vectors"], np.float64).reshape(len(ids), -1)


def _with_floors(asked: DataFrame, seed: dict | None, rotation: np.ndarray, k: int) -> DataFrame:
    """Adds ``floors``: each query's k-th best score among the candidates of one block."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                ids, queries = _block(row)
                best = _Best(len(ids), k)
                if seed is not None:
                    search_block(best, ids, queries, *_block(seed), rotation)
                yield pa.RecordBatch.from_pydict({"query_block": [row["query_block"]], "ids": [row["ids"]], "vectors": [row["vectors"]], "floors": [best.scores[:, -1].tobytes()]})

    return asked.select("query_block", "ids", "vectors").mapInArrow(run, "query_block long, ids binary, vectors binary, floors binary")


def top_products(rows: DataFrame, is_query, k: int = 5, scale: float = 256.0, groups: int | None = None, column: str = "embedding") -> DataFrame:
    """query_id, rank, vec_id, score: each query's k greatest integer inner products.

    ``is_query`` is a boolean Column over ``vec_id``; a query is no candidate of its own.
    ``groups`` (of candidates) follows from the number of rows unless it is given.
    """
    spark = rows.sparkSession
    rows = valid_vectors(rows.where("vec_id IS NOT NULL").select(F.col("vec_id").cast("long").alias("vec_id"), column), column)
    dimension = common_dimension(rows, column)
    quantised = rows.where(F.size(column) == max(1, dimension)).select("vec_id", F.transform(column, lambda x: F.floor(x * scale).cast("double")).alias("q"))
    rotation = _rotation(second_moments(quantised, max(1, dimension), "q")) if dimension else np.eye(1)
    sizes = quantised.agg(F.count("*").alias("n"), F.count(F.when(is_query, 1)).alias("q")).first()
    blocks, parts = -(-sizes["n"] // BLOCK), max(1, -(-sizes["q"] // (QUERY_BLOCK * CHUNK)))
    # at least a task for each core while there are blocks, at most CHUNK blocks in a group
    groups = groups or max(1, -(-blocks // CHUNK), min(blocks, 2 * spark.sparkContext.defaultParallelism // parts))
    length = F.aggregate("q", F.lit(0.0), lambda a, x: a + x * x)
    ordered = quantised.withColumn("length", length).repartitionByRange(groups, F.desc("length")).sortWithinPartitions(F.desc("length"), "vec_id")
    # a group is a range of lengths, so that few of its blocks stay open
    candidates = materialise(_packed(ordered, BLOCK, dimension, "block").withColumn("group", F.pmod(F.spark_partition_id().cast("long"), F.lit(groups))), "candidates")
    asked = materialise(_packed(quantised.where(is_query), QUERY_BLOCK, dimension, "query_block"), "asked")
    longest = candidates.orderBy(F.desc("longest"), "block").limit(1).select("ids", "vectors").collect()
    floored = materialise(_with_floors(asked, longest[0].asDict() if longest else None, rotation, k), "floored").withColumn("part", F.pmod(F.xxhash64("query_block"), F.lit(parts)))
    left = floored.withColumn("group", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(groups - 1).cast("long"))))
    right = candidates.withColumn("part", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(parts - 1).cast("long"))))

    def run(asked_: pa.Table, there: pa.Table) -> pa.Table:
        out: list[tuple[np.ndarray, ...]] = []
        blocks_ = [_block(r) for r in sorted(there.select(["ids", "vectors", "longest"]).to_pylist(), key=lambda r: -r["longest"])]
        for row in asked_.select(["ids", "vectors", "floors"]).to_pylist() if blocks_ else ():
            who, queries = _block(row)
            best = _Best(len(who), k, np.frombuffer(row["floors"], np.int64))
            for ids, vectors in blocks_:
                search_block(best, who, queries, ids, vectors, rotation)
            fine = best.ids != np.iinfo(np.int64).max
            out.append((np.repeat(who, k)[fine.ravel()], best.ids[fine], best.scores[fine]))
        columns = [np.concatenate(x) for x in zip(*out)] if out else [np.empty(0, np.int64)] * 3
        return pa.table({n: pa.array(x, pa.int64()) for n, x in zip(("query_id", "vec_id", "score"), columns)})

    found = left.groupBy("group", "part").cogroup(right.groupBy("group", "part")).applyInArrow(run, "query_id long, vec_id long, score long")
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
