"""Attacks on released vectors: reconstruction, linkage, membership."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import imaging, project, spectra
from .moments import block
from .release import PrivateEigenModel


def training_set(images: DataFrame, n: int = 1000, augment: bool = True) -> DataFrame:
    """The first n images by id, each also with its rows in reverse order."""
    first = images.orderBy("id").limit(n)
    return first.unionByName(imaging.vertical_flip(first)) if augment else first


def fit_attacker(images: DataFrame, components: int = 2000, n: int = 1000, augment: bool = True) -> spectra.EigenModel:
    return spectra.fit(training_set(images, n, augment), components)


def reconstruct(df: DataFrame, model: spectra.EigenModel, column: str = "pv", out: str = "guess", add_mean: bool = False, domain: str = "pixel", edge: PrivateEigenModel | None = None) -> DataFrame:
    """The sum over eigenvectors of their product with the noisy vector, times the eigenvector.

    With an ``edge`` the released values are scaled back by its bounds first.  In the
    score domain they then are the coefficients themselves; in the pixel domain they are
    pixels around the edge's mean.
    """
    sent = df.sparkSession.sparkContext.broadcast((model.mean, model.vectors, None if edge is None else (edge.bounds.lo, edge.bounds.hi, edge.eigen.mean)))

    def make():
        mean, vectors, bounds = sent.value

        def work(x: np.ndarray) -> np.ndarray:
            if bounds is not None:
                x = bounds[0] + x * (bounds[1] - bounds[0])
                x = x + (bounds[2] - mean) if domain == "pixel" else x
            coefficients = x @ vectors.T if domain == "pixel" else x
            return coefficients @ vectors + (mean if add_mean else 0.0)

        return work

    return project.mapped(df, column, out, None, make)


def coordinates(df: DataFrame, model: spectra.EigenModel, column: str, out: str = "v", digits: int = 10) -> DataFrame:
    """``df`` with, instead of ``column``, its products with the eigenvectors and its distance from what they span.

    Between an image and a vector in the span the distance stays what it is; rounded, so
    that equal images keep equal coordinates in any batch.
    """
    sent = df.sparkSession.sparkContext.broadcast((model.mean, model.vectors))

    def make():
        mean, vectors = sent.value

        def work(x: np.ndarray) -> np.ndarray:
            x = x - mean
            c = x @ vectors.T
            rest = np.sqrt(((x - c @ vectors) ** 2).sum(1, keepdims=True))
            return np.round(np.hstack([c, rest]), digits) + 0.0

        return work

    return project.mapped(df, column, out, len(model.mean), make)


def packed(df: DataFrame, vector: str, keep: tuple[str, ...] = (), block_bytes: int = 4 << 20) -> DataFrame:
    """Rows in blocks of about ``block_bytes``, each in the order of ids, where they are: block, ids, x and lists of ``keep``."""

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x, ids = block(batch.column("v")), np.asarray(batch.column("id"))
            rows = max(1, block_bytes // (8 * max(1, x.shape[1])))
            for at in range(0, len(x), rows):
                order = at + np.argsort(ids[at : at + rows], kind="stable")
                lists = {c: pa.array([batch.column(c).take(pa.array(order)).to_pylist()], pa.list_(pa.float64())) for c in keep}
                yield pa.RecordBatch.from_pydict({"ids": pa.array([ids[order].tobytes()], pa.binary()), "x": pa.array([x[order].tobytes()], pa.binary()), **lists})

    rows = df.select(F.col("id").cast("long").alias("id"), F.col(vector).cast("array<double>").alias("v"), *[F.col(c).cast("double").alias(c) for c in keep])
    made = rows.mapInArrow(pack, ", ".join(["ids binary, x binary", *(f"{c} array<double>" for c in keep)]))
    return made.withColumn("block", F.monotonically_increasing_id())


def nearest_rate(probes: DataFrame, gallery: DataFrame, vector: str, block_bytes: int = 4 << 20) -> DataFrame:
    """Share of probes whose nearest gallery row (of ties the one with the least id) has their own id.

    Blocks of both sides are packed where the rows are and kept once, and each probe keeps
    its best over all blocks; no side is collected, bounded or copied for the other.
    """
    sides = [packed(df, vector, block_bytes=block_bytes).persist() for df in (probes, gallery)]
    done = nearest_of(*sides)
    for side in sides:
        side.unpersist()
    return done


def nearest_of(probes: DataFrame, gallery: DataFrame, keep: tuple[str, ...] = (), part_bytes: int = 32 << 20) -> DataFrame:
    """``nearest_rate`` of kept blocks, with the means of ``keep`` over the probes; computed now.

    A task takes blocks of one part of the probes and about ``part_bytes`` of the gallery,
    and gives the best of each probe there.
    """
    spark = probes.sparkSession
    held = gallery.agg(F.sum(F.length("x"))).first()[0]
    if held is None:
        lists = [F.explode(F.arrays_zip(*keep)).alias("r")] if keep else []
        if keep:
            got = probes.select(*lists).agg(F.lit(None).cast("double").alias("rate"), F.count("*").alias("n"), *[F.avg(f"r.{c}").alias(c) for c in keep])
        else:
            got = probes.agg(F.lit(None).cast("double").alias("rate"), F.coalesce(F.sum(F.length("ids") / 8), F.lit(0)).cast("long").alias("n"))
        return spark.createDataFrame(got.toArrow())

    def match(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own, best, found, row = None, None, None, None

        def given() -> pa.RecordBatch:
            n = len(best)
            lists = [row.column(c).flatten() for c in keep]
            ids = np.frombuffer(row.column("ids")[0].as_py(), np.int64)
            return pa.RecordBatch.from_arrays([pa.array(np.full(n, own)), pa.array(np.arange(n)), pa.array(ids), pa.array(found), pa.array(best), *lists], ["p", "k", "id", "match", "score", *keep])

        for batch in batches:
            for i in range(batch.num_rows):
                name = batch.column("block")[i].as_py()
                if name != own:  # pairs of a block of probes follow one another
                    if own is not None:
                        yield given()
                    own, row = name, batch.slice(i, 1).select(["ids", *keep])
                    n = len(row.column("ids")[0].as_py()) // 8
                    x = np.frombuffer(batch.column("x")[i].as_py()).reshape(n, -1)
                    best, found = np.full(n, -np.inf), np.full(n, np.iinfo(np.int64).max)
                names = np.frombuffer(batch.column("names")[i].as_py(), np.int64)
                known = np.frombuffer(batch.column("y")[i].as_py()).reshape(len(names), -1)
                half, step = (known**2).sum(1) / 2, max(1, (4 << 20) // len(names))
                for at in range(0, len(x), step):
                    score = x[at : at + step] @ known.T - half
                    near = score.argmax(1)
                    score, near = score[np.arange(len(near)), near], names[near]
                    here = slice(at, at + len(near))
                    better = (score > best[here]) | ((score == best[here]) & (near < found[here]))
                    best[here], found[here] = np.where(better, score, best[here]), np.where(better, near, found[here])
        if own is not None:
            yield given()

    right = gallery.select(F.col("ids").alias("names"), F.col("x").alias("y")).coalesce(max(1, -(-held // part_bytes)))
    schema = ", ".join(["p long, k long, id long, match long, score double", *(f"{c} double" for c in keep)])
    met = probes.crossJoin(right).select("block", "ids", "x", *keep, "names", "y").mapInArrow(match, schema)
    most = met.groupBy("p", "k").agg(F.max(F.struct("score", (-F.col("match")).alias("back"), "id", *keep)).alias("b"))
    got = most.agg(F.avg((-F.col("b.back") == F.col("b.id")).cast("int")).alias("rate"), F.count("*").alias("n"), *[F.avg(f"b.{c}").alias(c) for c in keep])
    return spark.createDataFrame(got.toArrow())


def link(rel_a: DataFrame, rel_b: DataFrame, column: str = "pv") -> DataFrame:
    """Q13: how often the nearest vector of another release is the same record's."""
    return nearest_rate(rel_a, rel_b, column)


def membership(scored: DataFrame, score: str = "confidence", member: str = "member") -> DataFrame:
    """Q14: the greatest advantage of a threshold on confidence in telling members from others."""
    by_value = scored.groupBy(F.col(score).alias("s")).agg(F.sum(F.col(member).cast("int")).alias("inside"), F.sum(1 - F.col(member).cast("int")).alias("outside"))
    totals = by_value.agg(F.sum("inside").alias("ti"), F.sum("outside").alias("to"))
    # running sums in two steps, so that no task orders all values: within a thousandth of the range, and over these
    binned = by_value.withColumn("bin", F.floor(F.col("s") * 1000))
    inner = Window.partitionBy("bin").orderBy(F.desc("s"))
    outer = Window.orderBy(F.desc("bin")).rowsBetween(Window.unboundedPreceding, -1)
    bins = binned.groupBy("bin").agg(F.sum("inside").alias("bi"), F.sum("outside").alias("bo"))
    before = bins.select("bin", F.coalesce(F.sum("bi").over(outer), F.lit(0)).alias("pi"), F.coalesce(F.sum("bo").over(outer), F.lit(0)).alias("po"))
    within = binned.select("bin", F.sum("inside").over(inner).alias("wi"), F.sum("outside").over(inner).alias("wo"))
    running = within.join(before, "bin").select((F.col("pi") + F.col("wi")).alias("i"), (F.col("po") + F.col("wo")).alias("o")).crossJoin(F.broadcast(totals))
    return running.agg(F.greatest(F.lit(0.0), F.max(F.col("i") / F.col("ti") - F.col("o") / F.col("to"))).alias("advantage"))


def memorisation_gap(train: DataFrame, test: DataFrame) -> DataFrame:
    """Training minus test accuracy and mean confidence, rows with label, pred and confidence."""
    sides = [x.agg(F.avg((F.col("label") == F.col("pred")).cast("int")).alias(f"acc_{n}"), F.avg("confidence").alias(f"conf_{n}")) for n, x in (("train", train), ("test", test))]
    both = sides[0].crossJoin(sides[1])
    return both.select((F.col("acc_train") - F.col("acc_test")).alias("accuracy_gap"), (F.col("conf_train") - F.col("conf_test")).alias("confidence_gap"))
