"""Eigenfaces by several routes and the checks that hold for each."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .moments import Moments, block, mean_face, moments, partials, unpacked

#: Bytes of products of rows that the Gram route may hold on the driver.
GRAM_LIMIT = 1 << 30
DIRECT_LIMIT = 8192


@dataclass
class EigenModel:
    mean: np.ndarray
    values: np.ndarray
    vectors: np.ndarray  # components x pixels, unit length
    n: int
    w: int = 0
    h: int = 0
    ch: int = 1

    @property
    def nc(self) -> int:
        return len(self.values)

    def take(self, nc: int) -> EigenModel:
        return EigenModel(self.mean, self.values[:nc], self.vectors[:nc], self.n, self.w, self.h, self.ch)


def top_components(values: np.ndarray, vectors: np.ndarray, nc: int) -> tuple[np.ndarray, np.ndarray]:
    """The nc largest, as rows of unit length whose entry of greatest magnitude is positive."""
    keep = np.argsort(-values, kind="stable")[:nc]
    rows = vectors[:, keep].T
    rows = rows / np.maximum(np.linalg.norm(rows, axis=1, keepdims=True), 1e-300)
    signs = np.sign(rows[np.arange(len(rows)), np.abs(rows).argmax(1)])
    return values[keep], rows * np.where(signs == 0, 1, signs)[:, None]


def solve_direct(state: Moments, nc: int, ddof: int = 1, used_up: bool = False) -> EigenModel:
    """Eigenvectors of the covariance itself, which takes the place of the scatter if the state is ``used_up``."""
    if used_up and state.n > ddof:
        state.scatter /= state.n - ddof
    values, vectors = np.linalg.eigh(state.scatter if used_up and state.n > ddof else state.covariance(ddof))
    return EigenModel(state.mean, *top_components(values, vectors, nc), state.n)


def _packed_blocks(df: DataFrame, column: str, rows: int = 512) -> DataFrame:
    """block, n and x: rows packed in the order of their partitions."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, rows):
                x = block(batch.column(0).slice(at, rows))
                yield pa.RecordBatch.from_pydict({"n": pa.array([len(x)], pa.int64()), "x": pa.array([x.tobytes()], pa.binary())})

    return df.select(column).mapInArrow(run, "n long, x binary").withColumn("block", F.monotonically_increasing_id())


def gram(rows: np.ndarray) -> np.ndarray:
    return rows @ rows.T


def gram_blocks(packed: DataFrame) -> DataFrame:
    """a, b and p: the products of the rows of each pair of blocks a <= b, by an equi-join of block pairs."""
    names = packed.select("block")
    left = packed.select(F.col("block").alias("a"), F.col("n").alias("m"), F.col("x").alias("u"))
    right = packed.select(F.col("block").alias("b"), "n", F.col("x").alias("v"))
    pairs = names.select(F.col("block").alias("a")).crossJoin(names.select(F.col("block").alias("b"))).where("a <= b")
    met = pairs.join(left, "a").join(right, "b")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for r in batch.to_pylist():
                x, y = np.frombuffer(r["u"]).reshape(r["m"], -1), np.frombuffer(r["v"]).reshape(r["n"], -1)
                yield pa.RecordBatch.from_pydict({"a": [r["a"]], "b": [r["b"]], "p": pa.array([(x @ y.T).tobytes()], pa.binary())})

    return met.select("a", "b", "m", "n", "u", "v").mapInArrow(run, "a long, b long, p binary")


def solve_gram(df: DataFrame, nc: int, column: str = "px", ddof: int = 1, chunk: int = 64) -> EigenModel:
    """Eigenvectors of the products of rows, lifted by the rows.

    Products are made by pairs of row blocks and the lift by each block, both over tasks;
    the driver holds the n x n products, whose size is checked, and the eigenfaces.  More
    rows than pixels are first turned to as many rows as pixels (``_turned``).
    """
    packed = _packed_blocks(df, column).persist()
    try:
        sizes = {r["block"]: r["n"] for r in packed.select("block", "n").collect()}
        n = sum(sizes.values())
        if not n:
            raise ValueError("no rows")
        mean = mean_face(df, column)
        if min(n, len(mean)) ** 2 * 8 > GRAM_LIMIT:
            raise ValueError("the Gram route is for small cohorts or images")
        if n > len(mean):
            few = _turned(packed, mean)
            values, left = _leading(gram(few), nc)
            return EigenModel(mean, *top_components(values / (n - ddof), few.T @ left, nc), n)
        at, total = {}, 0
        for name in sorted(sizes):
            at[name], total = total, total + sizes[name]
        k = np.zeros((n, n))
        for r in gram_blocks(packed).toLocalIterator():
            part = np.frombuffer(bytes(r["p"])).reshape(sizes[r["a"]], sizes[r["b"]])
            k[at[r["a"]] : at[r["a"]] + len(part), at[r["b"]] : at[r["b"]] + part.shape[1]] = part
            k[at[r["b"]] : at[r["b"]] + part.shape[1], at[r["a"]] : at[r["a"]] + len(part)] = part.T
        # products of centred rows
        k -= k.mean(0)
        k -= k.mean(1, keepdims=True)
        values, left = _leading(k, nc)
        lifted = _lifted(packed, at, mean, left, chunk)
    finally:
        packed.unpersist()
    return EigenModel(mean, *top_components(values / (n - ddof), lifted, nc), n)


def _leading(k: np.ndarray, nc: int) -> tuple[np.ndarray, np.ndarray]:
    """The ``nc`` largest eigenvalues of the products that are not zero, with their vectors as columns."""
    values, left = np.linalg.eigh((k + k.T) / 2)
    order = np.argsort(-values)[:nc]
    order = order[values[order] > 1e-10 * max(values.max(), 1e-300)]
    return values[order], left[:, order]


def _turned(packed: DataFrame, mean: np.ndarray, width: int = 8) -> np.ndarray:
    """The centred rows under an orthogonal turn that leaves as many of them as pixels: what they lift to is the same.

    Each task folds its blocks into a triangular factor, and factors meet in a tree, eight at a time.
    """
    sent = packed.sparkSession.sparkContext.broadcast(mean)
    d = len(mean)

    def fold(batches: Iterator[pa.RecordBatch], centre) -> Iterator[pa.RecordBatch]:
        held = np.empty((0, d))
        for batch in batches:
            for x in batch.column("x").to_pylist():
                held = np.vstack([held, np.frombuffer(x).reshape(-1, d) - centre])
                if len(held) > 2 * d:
                    held = np.linalg.qr(held, mode="r")
        if len(held):
            yield pa.RecordBatch.from_pydict({"x": pa.array([(np.linalg.qr(held, mode="r") if len(held) > d else held).tobytes()], pa.binary())})

    parts, tasks = packed.select("x").mapInArrow(lambda batches: fold(batches, sent.value), "x binary"), packed.rdd.getNumPartitions()
    while tasks > width:
        tasks = -(-tasks // width)
        parts = parts.repartition(tasks).mapInArrow(lambda batches: fold(batches, 0.0), "x binary")
    last = parts.coalesce(1).mapInArrow(lambda batches: fold(batches, 0.0), "x binary").first()
    return np.frombuffer(bytes(last["x"])).reshape(-1, d)


def _lifted(packed: DataFrame, at: dict[int, int], mean: np.ndarray, left: np.ndarray, chunk: int) -> np.ndarray:
    """Centred rows, transposed, times ``left``: partial sums per task and chunk of columns, added per chunk."""
    sent = packed.sparkSession.sparkContext.broadcast((at, mean, left))
    d, width = len(mean), left.shape[1]

    def part(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        places, centre, turn = sent.value
        total = None
        for batch in batches:
            for r in batch.to_pylist():
                x = np.frombuffer(r["x"]).reshape(r["n"], -1) - centre
                got = x.T @ turn[places[r["block"]] : places[r["block"]] + r["n"]]
                total = got if total is None else total + got
        if total is not None:
            for c in range(0, width, chunk):
                yield pa.RecordBatch.from_pydict({"c": [c], "s": pa.array([total[:, c : c + chunk].tobytes()], pa.binary())})

    def add(table: pa.Table) -> pa.Table:
        sums = sum(np.frombuffer(x) for x in table.column("s").to_pylist())
        return pa.table({"c": table.column("c")[:1], "s": pa.array([sums.tobytes()], pa.binary())})

    parts = packed.select("block", "n", "x").mapInArrow(part, "c long, s binary")
    out = np.zeros((d, width))
    for r in parts.groupBy("c").applyInArrow(add, "c long, s binary").collect():
        got = np.frombuffer(bytes(r["s"])).reshape(d, -1)
        out[:, r["c"] : r["c"] + got.shape[1]] = got
    return out


def solve_subspace(df: DataFrame, nc: int, column: str = "px", oversample: int = 8, iters: int = 30, tol: float = 1e-6, ddof: int = 1, seed: int = 5) -> EigenModel:
    """Subspace iteration; each pass sends d x (nc + oversample) numbers and sums as many per task."""
    spark = df.sparkSession
    mean = mean_face(df, column)
    d = len(mean)
    k = min(d, nc + oversample)
    basis = np.linalg.qr(np.random.default_rng(seed).normal(size=(d, k)))[0]
    before, n = None, 0
    for _ in range(iters):
        sent = spark.sparkContext.broadcast((mean, basis))

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            centre, q = sent.value
            rows, total = 0, np.zeros_like(q)
            for batch in batches:
                x = block(batch.column(0))
                if len(x):
                    x = x - centre
                    rows, total = rows + len(x), total + x.T @ (x @ q)
            yield pa.RecordBatch.from_pydict({"n": pa.array([rows]), "y": pa.array([total.tobytes()], pa.binary())})

        got = df.select(column).mapInArrow(run, "n long, y binary").collect()
        n = sum(r["n"] for r in got)
        y = sum(np.frombuffer(bytes(r["y"])).reshape(d, k) for r in got)
        inner = basis.T @ y
        values, turn = np.linalg.eigh((inner + inner.T) / 2)
        order = np.argsort(-values)
        values, vectors = values[order], basis @ turn[:, order]
        basis = np.linalg.qr(y)[0]
        sent.unpersist()
        if before is not None and np.all(np.abs(values[:nc] - before[:nc]) <= tol * np.abs(values[0])):
            break
        before = values
    return EigenModel(mean, *top_components(values / (n - ddof), vectors, nc), n)


def solve_mllib(df: DataFrame, nc: int, column: str = "px") -> EigenModel:
    """The library's principal components, as a cross-check."""
    from pyspark.ml.feature import PCA
    from pyspark.ml.functions import array_to_vector

    state = moments(df, column)
    fitted = PCA(k=nc, inputCol="v", outputCol="p").fit(df.select(array_to_vector(F.col(column).cast("array<double>")).alias("v")))
    vectors = fitted.pc.toArray()
    values = np.einsum("dk,de,ek->k", vectors, state.covariance(), vectors)
    return EigenModel(state.mean, *top_components(values, vectors, nc), state.n)


def plan_route(n: int, d: int) -> str:
    """The Gram route for fewer rows than pixels, subspace iteration where a d x d matrix is too large."""
    if n < d and n * n * 8 <= GRAM_LIMIT:
        return "gram"
    return "direct" if d <= DIRECT_LIMIT else "subspace"


def fit(df: DataFrame, nc: int, column: str = "px", ddof: int = 1, route: str | None = None, n: int | None = None) -> EigenModel:
    """A2: distributed eigenfaces by the route that the sizes call for; ``n`` rows, counted here if not given."""
    if route is None:
        first = df.select(column).first()
        if first is None:
            raise ValueError("no rows")
        route = plan_route(df.count() if n is None else n, len(first[0]))
    if route == "gram":
        return solve_gram(df, nc, column, ddof)
    if route == "subspace":
        return solve_subspace(df, nc, column, ddof=ddof)
    return solve_direct(moments(df, column), nc, ddof, used_up=True)


def fit_local(rows: np.ndarray, nc: int, ddof: int = 1) -> EigenModel:
    """Eigenfaces of an array in one process."""
    return solve_direct(Moments.of(rows), nc, ddof)


def fit_one_task(df: DataFrame, nc: int, column: str = "px", ddof: int = 1) -> EigenModel:
    """A1 / B4 for rows of any number: one task reads them all, batch by batch, and holds one state."""
    row = partials(df.coalesce(1), column).first()
    if row is None:
        raise ValueError("no rows")
    return solve_direct(unpacked(row), nc, ddof, used_up=True)


def eigen_checks(covariance: np.ndarray, model: EigenModel) -> dict[str, float]:
    """Q16: residual, distance from orthonormal, trace and squared norm against the eigenvalues, share explained."""
    v = model.vectors
    return {
        "residual": float(np.abs(covariance @ v.T - v.T * model.values).max()),
        "orthonormal": float(np.abs(v @ v.T - np.eye(len(v))).max()),
        "trace": float(np.trace(covariance)),
        "sum_values": float(model.values.sum()),
        "frobenius": float((covariance**2).sum()),
        "sum_squares": float((model.values**2).sum()),
        "share": float(model.values.sum() / np.trace(covariance)),
    }


def same_subspace(a: np.ndarray, b: np.ndarray) -> float:
    """Greatest difference of the projectors on two row spaces."""
    return float(np.abs(a.T @ a - b.T @ b).max())


def choose_nc(curve: list[tuple[int, float]], tol: float = 0.01) -> int:
    """The first count after which a further step gains less than ``tol`` per step of the sweep."""
    curve = sorted(curve)
    for (nc, score), (_, following) in zip(curve, curve[1:]):
        if following - score < tol:
            return nc
    return curve[-1][0]
