"""Relational helpers around the methods."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def with_targets(vectors: DataFrame, labels: DataFrame, on: str = "doc_id", how: str = "inner") -> DataFrame:
    return vectors.join(labels, on, how)


def keep_known(df: DataFrame, roster: DataFrame, on) -> DataFrame:
    return df.join(roster, on, "left_semi")


def drop_revoked(df: DataFrame, revoked: DataFrame, on) -> DataFrame:
    return df.join(revoked, on, "left_anti")


def hinted_join(a: DataFrame, b: DataFrame, on, hint: str, how: str = "inner") -> DataFrame:
    """broadcast, merge, shuffle_hash or shuffle_replicate_nl: one result by different plans."""
    return a.join(b.hint(hint), on, how)


def hinted_slices(a: DataFrame, b: DataFrame, on: str, hint: str, rows: int = 500_000) -> Iterator[DataFrame]:
    """The parts of ``hinted_join``, one after the other: to broadcast more than ``rows`` rows, keys are cut into slices.

    Each slice of ``b`` is a broadcast of its own, so that a caller who is done with one
    part before it takes the next holds about ``rows`` rows at a time, whatever the table.
    """
    n = max(1, -(-b.count() // rows)) if hint == "broadcast" else 1
    for k in range(n):
        mine = F.pmod(F.xxhash64(F.col(on).cast("string")), F.lit(n)) == k
        yield hinted_join(a.where(mine), b.where(mine), on, hint) if n > 1 else hinted_join(a, b, on, hint)


def asof_latest(left: DataFrame, right: DataFrame, by: str, lt: str, rt: str, value: str) -> DataFrame:
    """Each left row with the value of the last right row of its key at or before its time.

    One union sorted once per key: no join, no row multiplied.
    """
    a = left.withColumn("__t", F.col(lt)).withColumn("__side", F.lit(1)).withColumn("__v", F.lit(None).cast(right.schema[value].dataType))
    b = right.select(by, F.col(rt).alias("__t"), F.lit(0).alias("__side"), F.col(value).alias("__v"))
    both = a.unionByName(b, allowMissingColumns=True)
    w = Window.partitionBy(by).orderBy("__t", "__side").rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn("latest", F.last("__v", ignorenulls=True).over(w)).where("__side = 1").drop("__t", "__side", "__v")


def within_interval(left: DataFrame, right: DataFrame, by: str, lt: str, rt: str, tol: int) -> DataFrame:
    """Pairs whose times (whole seconds) differ by at most ``tol``: equi-join on buckets of that width."""
    l = left.withColumn("__b", F.explode(F.array(*[F.floor(F.col(lt) / tol) + k for k in (-1, 0, 1)])))
    r = right.withColumn("__b", F.floor(F.col(rt) / tol))
    return l.join(r, [by, "__b"]).where(F.abs(F.col(lt) - F.col(rt)) <= tol).drop("__b")


def range_match(values: DataFrame, bins: DataFrame, column: str, width: float) -> DataFrame:
    """Each value with the [lo, hi) bin that holds it; bins are cut to buckets of ``width`` and met by equality."""
    v = values.withColumn("__b", F.floor(F.col(column) / width))
    b = bins.withColumn("__b", F.explode(F.sequence(F.floor(F.col("lo") / width), F.floor(F.col("hi") / width))))
    return v.join(F.broadcast(b), "__b").where((F.col(column) >= F.col("lo")) & (F.col(column) < F.col("hi"))).drop("__b")


def in_blocks(a: DataFrame, b: DataFrame, compute: Callable, schema: str, rows: int = 1024) -> DataFrame:
    """``compute(ids, x, other ids, y)`` for each pair of packed blocks of ``a(id, v)`` and ``b(id, v)``; its columns as rows.

    Rows are dealt to blocks of about ``rows`` by a hash, and each block meets each block
    of the other side: no row is joined with a row, and no side is collected.
    """
    p, q = (max(1, -(-x.count() // rows)) for x in (a, b))

    def pack(part: pa.Table) -> pa.Table:
        part = part.combine_chunks()
        x = np.array(part.column("v").to_pylist(), np.float64)
        return pa.table({"own": part.column("own")[:1], "ids": pa.array([np.asarray(part.column("id"), np.int64).tobytes()], pa.binary()), "x": pa.array([x.tobytes()], pa.binary())})

    def side(df: DataFrame, own: str, blocks: int, other: str, others: int) -> DataFrame:
        dealt = df.select(F.col("id").cast("long").alias("id"), F.col("v").cast("array<double>").alias("v")).withColumn("own", F.pmod(F.xxhash64("id", "v"), F.lit(blocks)))
        packed = dealt.groupBy("own").applyInArrow(pack, "own long, ids binary, x binary").withColumnRenamed("own", own)
        return packed.withColumn(other, F.explode(F.sequence(F.lit(0).cast("long"), F.lit(others - 1).cast("long"))))

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        ids, x, names, y = np.empty(0, np.int64), np.empty((0, 0)), np.empty(0, np.int64), np.empty((0, 0))
        if left.num_rows and right.num_rows:
            ids, names = (np.frombuffer(t.column("ids")[0].as_py(), np.int64) for t in (left, right))
            x, y = (np.frombuffer(t.column("x")[0].as_py()).reshape(len(i), -1) for t, i in ((left, ids), (right, names)))
        return pa.table(compute(ids, x, names, y))

    sides = side(a, "p", p, "q", q), side(b, "q", q, "p", p)
    return sides[0].groupBy("p", "q").cogroup(sides[1].groupBy("p", "q")).applyInArrow(run, schema)


def _distances(x: np.ndarray, y: np.ndarray, power: int = 2) -> Iterator[tuple[slice, np.ndarray]]:
    """Sums of squared (or absolute) differences, for slices of ``x``."""
    for at in range(0, len(x), 32):
        part = slice(at, min(at + 32, len(x)))
        apart = x[part, None, :] - y[None]
        yield part, (apart * apart if power == 2 else np.abs(apart)).sum(2)


def close_pairs(df: DataFrame, limit: float, rows: int = 1024) -> DataFrame:
    """(a, b), a < b, whose squared distance is under ``limit``, in blocks; df has id and v."""

    def compute(ids, x, names, y):
        out = [(ids[part][i], names[j]) for part, d in (_distances(x, y) if len(ids) else ()) for i, j in [np.nonzero((d < limit) & (ids[part][:, None] < names[None]))]]
        a, b = (np.concatenate(z) for z in zip(*out)) if out else (np.empty(0, np.int64),) * 2
        return {"a": pa.array(a, pa.int64()), "b": pa.array(b, pa.int64())}

    return in_blocks(df, df, compute, "a long, b long", rows)


def greatest_l1(df: DataFrame, rows: int = 1024) -> DataFrame:
    """The greatest L1 distance of two rows, in blocks: one number per pair of blocks."""

    def compute(ids, x, names, y):
        most = [float(d.max()) for _, d in (_distances(x, y, 1) if len(ids) else ())]
        return {"d": pa.array([max(most)] if most else [], pa.float64())}

    return in_blocks(df, df, compute, "d double", rows).agg(F.max("d").alias("delta"))


def row_products(df: DataFrame, rows: int = 8192, step: int = 1 << 20) -> DataFrame:
    """(a, b, dot) of all rows: large packed blocks, sent once for each block of the other side, give ``step`` products at a time."""
    n = df.count()
    blocks = max(1, -(-n // rows), min(8, -(-n // 1024)))

    def pack(part: pa.Table) -> pa.Table:
        part = part.combine_chunks()
        x = np.array(part.column("v").to_pylist(), np.float64)
        return pa.table({"own": part.column("own")[:1], "ids": pa.array([np.asarray(part.column("id"), np.int64).tobytes()], pa.binary()), "x": pa.array([x.tobytes()], pa.binary())})

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k in range(batch.num_rows):
                ids, names = (np.frombuffer(batch.column(c)[k].as_py(), np.int64) for c in ("ids", "names"))
                x, y = (np.frombuffer(batch.column(c)[k].as_py()).reshape(len(i), -1) for c, i in (("x", ids), ("y", names)))
                each = max(1, step // len(names))
                for at in range(0, len(ids), each):
                    part = ids[at : at + each]
                    dot = x[at : at + each] @ y.T
                    yield pa.RecordBatch.from_arrays([pa.array(np.repeat(part, len(names))), pa.array(np.tile(names, len(part))), pa.array(dot.ravel())], ["a", "b", "dot"])

    dealt = df.select(F.col("id").cast("long").alias("id"), F.col("v").cast("array<double>").alias("v")).withColumn("own", F.pmod(F.xxhash64("id", "v"), F.lit(blocks)))
    packed = dealt.groupBy("own").applyInArrow(pack, "own long, ids binary, x binary")
    left = packed.select("ids", "x", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(blocks - 1).cast("long"))).alias("other"))
    right = packed.select(F.col("own").alias("other"), F.col("ids").alias("names"), F.col("x").alias("y"))
    return left.join(right, "other").select("ids", "x", "names", "y").mapInArrow(run, "a long, b long, dot double")


def theta_pairs(a: DataFrame, b: DataFrame, predicate: Column) -> DataFrame:
    """Nested-loop pairs, for audits of stated small sets."""
    return a.crossJoin(b).where(predicate)


def nearest_one(probe: DataFrame, gallery: DataFrame, vector: str = "v") -> DataFrame:
    """The nearest gallery row of each probe by squared distance (nine digits); ties go to the smaller id.

    Packed blocks meet, and each keeps the best of its rows.
    """

    def compute(ids, x, names, y):
        out = []
        order = np.argsort(names, kind="stable")
        names, y = names[order], y[order] if len(order) else y
        for part, d in _distances(x, y) if len(ids) else ():
            d = np.where(ids[part][:, None] == names[None], np.inf, np.round(d, 9))
            best = d.argmin(1)
            out.append((ids[part], names[best], d[np.arange(len(best)), best]))
        who, found, far = (np.concatenate(z) for z in zip(*out)) if out else (np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0))
        fine = np.isfinite(far)
        return {"id": pa.array(who[fine], pa.int64()), "gid": pa.array(found[fine], pa.int64()), "d": pa.array(far[fine], pa.float64())}

    sides = [df.select("id", F.col(vector).alias("v")) for df in (probe, gallery)]
    pairs = in_blocks(*sides, compute, "id long, gid long, d double")
    return pairs.groupBy("id").agg(F.min(F.struct("d", "gid")).alias("m")).select("id", F.col("m.gid").alias("match"), F.col("m.d").alias("dist"))


def cube_metrics(df: DataFrame, keys: list[str], *aggs: Column) -> DataFrame:
    return df.cube(*keys).agg(F.grouping_id().cast("long").alias("gid"), *aggs)


def rollup_metrics(df: DataFrame, keys: list[str], *aggs: Column) -> DataFrame:
    return df.rollup(*keys).agg(F.grouping_id().cast("long").alias("gid"), *aggs)


def top_k(df: DataFrame, by: list[Column], k: int) -> DataFrame:
    return df.orderBy(*by).limit(k)


def top_k_per(df: DataFrame, key: str, by: list[Column], k: int, salt: Column | None = None, parts: int = 32) -> DataFrame:
    """The first k rows of each key; with a salt a first cut per (key, part) keeps a hot key out of one task."""
    if salt is not None:
        first = Window.partitionBy(key, "__p").orderBy(*by)
        df = df.withColumn("__p", F.pmod(F.xxhash64(salt), F.lit(parts))).withColumn("__n", F.row_number().over(first)).where(F.col("__n") <= k).drop("__p", "__n")
    return df.withColumn("rank", F.row_number().over(Window.partitionBy(key).orderBy(*by))).where(F.col("rank") <= k)


def running(df: DataFrame, key: str, order: list[str], column: str, width: int = 3) -> DataFrame:
    """Running sum, moving mean, lag, lead, first, last and second value of a column."""
    w = Window.partitionBy(key).orderBy(*order)
    past, whole = w.rowsBetween(Window.unboundedPreceding, 0), w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    made = {
        "running_sum": F.sum(column).over(past), "moving_mean": F.avg(column).over(w.rowsBetween(-(width - 1), 0)), "previous": F.lag(column).over(w), "following": F.lead(column).over(w),
        "first_value": F.first(column).over(whole), "last_value": F.last(column).over(whole), "second_value": F.nth_value(column, 2).over(whole),
    }
    return df.withColumns(made)


def moving_range(df: DataFrame, key: str, seconds: str, column: str, span: int) -> DataFrame:
    """Sum and count of a column over the ``span`` seconds up to each row (rows of equal time together)."""
    w = Window.partitionBy(key).orderBy(seconds).rangeBetween(-span, 0)
    return df.withColumn("span_sum", F.sum(column).over(w)).withColumn("span_n", F.count(column).over(w))


def ranks(df: DataFrame, key: str, order: list[Column]) -> DataFrame:
    w = Window.partitionBy(key).orderBy(*order)
    return df.withColumns({"rn": F.row_number().over(w), "rk": F.rank().over(w), "dr": F.dense_rank().over(w), "nt": F.ntile(4).over(w), "pr": F.percent_rank().over(w), "cd": F.cume_dist().over(w)})


def dedupe(df: DataFrame, keys: list[str], order: str) -> DataFrame:
    """The first row of each key by ``order``, by one partial aggregate."""
    rest = [c for c in df.columns if c not in keys]
    return df.groupBy(*keys).agg(F.min_by(F.struct(*rest), order).alias("__r"), F.count("*").alias("copies")).select(*keys, "__r.*", "copies")


def pivot_counts(df: DataFrame, row: str, column: str, values: list[str]) -> DataFrame:
    return df.groupBy(row).pivot(column, values).count().na.fill(0)


def unpivot_vector(df: DataFrame, id_: str, column: str) -> DataFrame:
    return df.select(id_, F.posexplode(column).alias("idx", "value"))


def parse_props(events: DataFrame) -> DataFrame:
    return events.withColumn("k", F.from_json("props", "k bigint")["k"])


def sample_keyed(df: DataFrame, frac: float, salt: str, id_: str) -> DataFrame:
    from ..functions import keyed_uniform

    return df.where(keyed_uniform(salt, F.col(id_).cast("string")) < frac)


def sample_strata(df: DataFrame, label: str, fractions: dict[str, float], salt: str, id_: str) -> DataFrame:
    from ..functions import keyed_uniform

    share = reduce(lambda e, kv: F.when(F.col(label) == kv[0], kv[1]).otherwise(e), fractions.items(), F.lit(0.0))
    return df.where(keyed_uniform(salt, F.col(id_).cast("string")) < share)
