"""What the private release is compared with."""

from __future__ import annotations

import math
import random
import time
from collections import Counter
from collections.abc import Iterator, Sequence
from dataclasses import dataclass, field
from functools import cached_property

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import keyed_uniform, laplace_icdf
from .moments import block
from .release import PrivateEigenModel, ReleasedFrame
from .residues import Residues


def no_privacy(model: PrivateEigenModel, df: DataFrame) -> ReleasedFrame:
    """B1: the same steps without noise."""
    return model.release(df, eps=None)


def raw_pixels(df: DataFrame) -> DataFrame:
    """B2: pixels as the recogniser's input."""
    return df.select("id", "label", F.col("px").cast("array<double>").alias("pv"))


def clean_scores(model: PrivateEigenModel, df: DataFrame) -> DataFrame:
    """Scaled scores, protected by nothing but the loss of dimensions."""
    return model.scaled(df).select("id", "label", F.col("scaled").alias("pv"))


def greedy_groups(x: np.ndarray, k: int) -> np.ndarray:
    """Group numbers: the first free row with its k - 1 nearest free rows; the rest joins the last group."""
    free, group, g = np.ones(len(x), bool), np.zeros(len(x), np.int64), 0
    while free.sum() >= 2 * k:
        i = int(np.flatnonzero(free)[0])
        left = np.flatnonzero(free)
        near = left[np.argsort(((x[left] - x[i]) ** 2).sum(1), kind="stable")[:k]]
        group[near], free[near] = g, False
        g += 1
    group[free] = g
    return group


def k_average(df: DataFrame, k: int, column: str = "px", bucket_rows: int = 2_000, seed: int = 3) -> DataFrame:
    """Groups of at least k nearby rows, each published as their mean.

    Beyond ``bucket_rows`` rows the greedy grouping runs within buckets of rows that are
    neighbours on a random direction; buckets are cut by rank, so none grows with the data.
    """
    n = df.count()
    buckets = max(1, n // bucket_rows)
    d = len(df.select(column).first()[0])
    direction = F.array(*map(F.lit, np.random.default_rng(seed).normal(size=d).tolist()))
    placed = df.select("id", "label", F.col(column).cast("array<double>").alias("x")).withColumn("t", F.aggregate(F.zip_with("x", direction, lambda a, b: a * b), F.lit(0.0), lambda s, v: s + v))
    edges = placed.agg(F.percentile_approx("t", [i / buckets for i in range(1, buckets)] or [0.5], 10_000).alias("e")).first()["e"] if buckets > 1 else []
    bucket = sum(((F.col("t") > e).cast("int") for e in edges), F.lit(0))

    def publish(part: pd.DataFrame) -> pd.DataFrame:
        part = part.sort_values("id", ignore_index=True)
        x = np.stack(part["x"].to_numpy())
        group = greedy_groups(x, k)
        means = np.stack([x[group == g].mean(0) for g in range(group.max() + 1)])
        return pd.DataFrame({"id": part["id"], "label": part["label"], "grp": part["bucket"].iloc[0] * 1_000_000 + group, "pv": list(means[group])})

    return placed.withColumn("bucket", bucket).groupBy("bucket").applyInPandas(publish, "id long, label string, grp long, pv array<double>")


def k_average_keyed(df: DataFrame, k: int, column: str = "px", salt: str = "kavg") -> DataFrame:
    """B7 with groups by keyed order instead of nearness, in long form (idx, value per group)."""
    # ranks by keyed order: counts of 256 digest ranges, then ranks within each range
    keyed = df.select("id", column).withColumn("o", F.md5(F.concat_ws("|", F.lit(salt), F.col("id").cast("string")))).withColumn("bin", F.substring("o", 1, 2))
    counts = keyed.groupBy("bin").agg(F.count("*").alias("c"))
    before = counts.select("bin", (F.sum("c").over(Window.orderBy("bin")) - F.col("c")).alias("before"), F.sum("c").over(Window.partitionBy()).alias("total"))
    place = F.row_number().over(Window.partitionBy("bin").orderBy("o", "id"))
    ranked = keyed.withColumn("r", place).join(F.broadcast(before), "bin")
    last = F.greatest(F.lit(0), F.floor(F.col("total") / k) - 1)
    grouped = ranked.select(F.least(F.floor((F.col("before") + F.col("r") - 1) / k), last).cast("long").alias("grp"), column)
    placed = grouped.select("grp", F.posexplode(column).alias("idx", "x"))
    return placed.groupBy("grp", "idx").agg(F.avg(F.col("x").cast("double")).alias("value"), F.count("*").alias("n"))


def global_laplace_mean(df: DataFrame, eps: float, key: str, column: str = "px", label: str = "label", lo: float = -1.0, hi: float = 1.0) -> DataFrame:
    """A trusted curator's class means of clipped vectors, with one draw per class and index.

    One person moves a mean of n vectors of k indexes in [lo, hi] by at most k (hi - lo) / n
    in L1 norm, which with eps gives the scale.
    """
    long = df.select(F.col(label).cast("string").alias("label"), F.size(column).alias("k"), F.posexplode(column).alias("idx", "x"))
    clipped = F.greatest(F.lit(lo), F.least(F.lit(hi), F.col("x").cast("double")))
    means = long.groupBy("label", "idx").agg(F.avg(clipped).alias("m"), F.count("*").alias("n"), F.max("k").alias("k"))
    u = keyed_uniform(key, "gdp", F.col("label"), F.col("idx").cast("string"))
    return means.select("label", "idx", "n", (F.col("m") + laplace_icdf(u, F.col("k") * F.lit(hi - lo) / (F.col("n") * eps))).alias("value"))


# --- B5, B6: matching under additive homomorphic encryption ------------------------


def _prime(bits: int, rng: random.Random) -> int:
    while True:
        n = rng.getrandbits(bits) | (1 << (bits - 1)) | 1
        if all(n % p for p in (3, 5, 7, 11, 13, 17, 19, 23, 29, 31)) and all(_strong(n, rng.randrange(2, n - 1)) for _ in range(16)):
            return n


def _strong(n: int, a: int) -> bool:
    d, r = n - 1, 0
    while d % 2 == 0:
        d, r = d // 2, r + 1
    x = pow(a, d, n)
    if x in (1, n - 1):
        return True
    return any((x := x * x % n) == n - 1 for _ in range(r - 1))


class Powers:
    """Powers of one number by tables of its powers: a product for each ``window`` bits of the exponent."""

    def __init__(self, base: int, modulus: int, bits: int, window: int = 7):
        self.modulus, self.window, self.tables = modulus, window, []
        for _ in range(max(1, -(-bits // window))):
            row = [1]
            for _ in range((1 << window) - 1):
                row.append(row[-1] * base % modulus)
            self.tables.append(row)
            base = row[-1] * base % modulus

    def times(self, c: int, exponent: int) -> int:
        """``c`` times the power."""
        low = (1 << self.window) - 1
        for table in self.tables:
            c = c * table[exponent & low] % self.modulus
            exponent >>= self.window
        return c


@dataclass
class Paillier:
    """Keys of the public additive scheme with generator n + 1; counts what it does.

    Ciphertexts are made random by powers of a public n-th residue with exponents of half
    the bits of n, taken from tables; the key holder opens them modulo each prime.
    """

    n: int
    p: int
    q: int
    seed: int = 0
    counts: Counter = field(default_factory=Counter)

    @classmethod
    def fresh(cls, bits: int = 256, seed: int = 1) -> Paillier:
        rng = random.Random(seed)
        p, q = _prime(bits // 2, rng), _prime(bits // 2, rng)
        while p == q:
            q = _prime(bits // 2, rng)
        return cls(p * q, p, q, seed)

    def __post_init__(self):
        self.square, self.half = self.n**2, self.n.bit_length() // 2
        base = random.Random(self.seed + 1).randrange(2, self.n)
        self.residues = Powers(pow(-base * base % self.n, self.n, self.square), self.square, self.half, 10)
        # of each prime: it, its square, and the inverse of what n + 1 opens to
        self.primes = [(p, p * p, pow(-other, -1, p)) for p, other in ((self.p, self.q), (self.q, self.p))]
        self.back = pow(self.p, -1, self.q)

    def encrypt(self, m: int, rng: random.Random) -> int:
        self.counts["encryptions"] += 1
        return self.residues.times(1 + m % self.n * self.n, rng.getrandbits(self.half))

    def _opened(self, c: int, k: int) -> int:
        p, square, turn = self.primes[k]
        return (pow(c % square, p - 1, square) - 1) // p * turn % p

    def decrypt(self, c: int, below_p: bool = False) -> int:
        """The value, from -n/2 to n/2; with ``below_p``, one known to be from 0 to p."""
        self.counts["decryptions"] += 1
        m = self._opened(c, 0)
        if below_p:
            return m
        m += (self._opened(c, 1) - m) * self.back % self.q * self.p
        return m - self.n if m > self.n // 2 else m

    @cached_property
    def group(self) -> Residues:
        return Residues(self.square)

    @cached_property
    def noise(self) -> np.ndarray:
        """The tables of ``residues``: (primes, windows, powers)."""
        tables = self.residues.tables
        return self.group.residues([v for row in tables for v in row]).reshape(-1, len(tables), len(tables[0]))

    @cached_property
    def openings(self) -> list[Residues]:
        return [Residues(square) for _, square, _ in self.primes]

    def encrypt_many(self, values: Sequence[int], rng: random.Random) -> np.ndarray:
        """``encrypt`` for all values at once, as residues of ``group``."""
        self.counts["encryptions"] += len(values)
        out, window = self.group.residues([1 + m % self.n * self.n for m in values]), self.residues.window
        exponents = [rng.getrandbits(self.half) for _ in values]
        for k in range(self.noise.shape[1]):
            part = [e >> window * k & (1 << window) - 1 for e in exponents]
            out = self.group.times(out, np.take(self.noise[:, k], part, 1))
        return out

    def decrypt_many(self, ciphertexts: Sequence[int], below_p: bool = False) -> list[int]:
        """``decrypt`` for all at once."""
        self.counts["decryptions"] += len(ciphertexts)
        opened = []
        for (p, square, turn), group in list(zip(self.primes, self.openings))[: 1 if below_p else 2]:
            powers = group.numbers(group.power(group.residues([c % square for c in ciphertexts]), p - 1))
            opened.append([(x - 1) // p * turn % p for x in powers])
        if below_p:
            return opened[0]
        both = [a + (b - a) * self.back % self.q * self.p for a, b in zip(*opened)]
        return [m - self.n if m > self.n // 2 else m for m in both]

    def add(self, a: int, b: int) -> int:
        self.counts["multiplications"] += 1
        return a * b % self.square

    def plus(self, c: int, m: int) -> int:
        """A known value added; it shares the randomness of ``c``."""
        return self.add(c, 1 + m % self.n * self.n)

    def times(self, c: int, k: int) -> int:
        self.counts["exponentiations"] += 1
        k %= self.n
        return pow(c, k if k <= self.n // 2 else k - self.n, self.square)


def match_encrypted(keys: Paillier, probe: list[int], gallery: dict[int, list[int]], basis: list[list[int]], offset: list[int], slots: int = 1, seed: int = 1) -> tuple[int, Counter]:
    """The id of the nearest gallery row, with the probe's pixels encrypted throughout.

    The gallery holder adds plaintext-weighted pixels to encrypted scores, has their
    squares made over one masked round trip, and forms encrypted squared distances; the
    key holder opens them under a common blinding that keeps their order.  ``slots``
    distances share one ciphertext, which divides rounds and decryptions.  The blinding and
    the slot go into the scores once, whose powers then come from tables, and each message
    is made random afresh.
    """
    rng = random.Random(seed)
    before = Counter(keys.counts)
    # the greatest blinded distance
    far = max(map(abs, probe), default=0)
    most = [sum(map(abs, row)) * far + abs(b) + max((abs(g[k]) for g in gallery.values()), default=0) for k, (row, b) in enumerate(zip(basis, offset))]
    greatest = (sum(x * x for x in most) << 16) + (1 << 40)
    width = 1 << (keys.n.bit_length() // slots - 2) if slots > 1 else 0
    if greatest >= (width or keys.n // 2):
        raise ValueError("distances are too large for the keys and slots")
    # slots no wider than the distances, if all of a ciphertext's then stay below one prime, which alone opens it
    below = greatest.bit_length() * slots < keys.p.bit_length()
    if below and slots > 1:
        width = 1 << greatest.bit_length()
    pixels = keys.encrypt_many(probe, rng)
    scores = []
    for b, (more, less) in zip(offset, _weighted(keys, pixels, basis)):
        scores.append(keys.add(keys.encrypt(-b, rng), more * pow(less, -1, keys.square)))
    # squares of the scores: masked values go to the key holder, come back squared
    squares = keys.encrypt(0, rng)
    for s in scores:
        mask = rng.randrange(1, 1 << 40)
        opened = keys.decrypt(keys.add(s, keys.encrypt(mask, rng)))
        back = keys.encrypt(opened * opened, rng)
        squares = keys.add(squares, keys.add(back, keys.add(keys.times(s, -2 * mask), keys.encrypt(-mask * mask, rng))))
    keys.counts["rounds"] += 1
    # a common factor and shift blind the distances without changing their order
    factor, shift = rng.randrange(1, 1 << 16), rng.randrange(1 << 40)
    top = [max((g[k] for g in gallery.values()), default=0) for k in range(len(scores))]
    bits = max((t - g[k] for g in gallery.values() for k, t in enumerate(top)), default=0).bit_length()
    # a score to the power -2x is one to the power -2 top, the same for all rows, times one to the power 2 (top - x)
    common = squares
    for s, t in zip(scores, top):
        common = keys.add(common, keys.times(s, -2 * t))
    group, ids, window = keys.group, list(gallery), 7
    steps = [[t - x for t, x in zip(top, g)] for g in gallery.values()]
    blind = [factor * sum(x * x for x in g) + shift for g in gallery.values()]
    shifts = [width**k if k else 1 for k in range(slots)]
    held = keys.encrypt_many([sum(x * w for x, w in zip(blind[at : at + slots], shifts)) for at in range(0, len(ids), slots)], rng)
    for k, by in enumerate(shifts):
        mine = steps[k::slots]
        if not mine:
            continue
        part = group.times(held[:, : len(mine)], group.residues([keys.times(common, factor * by)]))
        tables = group.tables(group.residues([keys.times(s, 2 * factor * by) for s in scores]), bits, window)
        for w in range(tables.shape[1]):
            for i in range(len(scores)):
                part = group.times(part, np.take(tables[:, w, i], [x[i] >> window * w & (1 << window) - 1 for x in mine], 1))
        held[:, : len(mine)] = part
    messages = group.numbers(held)
    keys.counts["exponentiations"] += len(scores) * len(ids)
    keys.counts["multiplications"] += (len(scores) + 1) * len(ids) + len(messages)
    keys.counts["bytes"] += keys.n.bit_length() // 4 * len(messages)
    keys.counts["rounds"] += len(messages)
    opened = keys.decrypt_many(messages, below)
    values = [v % keys.n // by % (width or keys.n) for v in opened for by in shifts]
    return min(zip(values, ids))[1], keys.counts - before


def _weighted(keys: Paillier, pixels: np.ndarray, basis: list[list[int]]) -> Iterator[tuple[int, int]]:
    """For each row of weights the product of powers of the pixels by its positive weights, and by the others turned positive."""
    group, weights = keys.group, np.array(basis, np.int64)
    bits, n = max(1, int(np.abs(weights).max(initial=0)).bit_length()), weights.shape[1]
    squares = [pixels]
    while len(squares) < bits:
        squares.append(group.times(squares[-1], squares[-1]))
    powers = np.concatenate(squares, 1)[:, None]
    step = max(1, 8192 // max(1, n * bits))
    for at in range(0, len(weights), step):
        signed = np.stack([np.maximum(weights[at : at + step], 0), np.maximum(-weights[at : at + step], 0)], 1).reshape(-1, 1, n)
        asked = (signed >> np.arange(bits)[:, None] & 1 > 0).reshape(len(signed), -1)
        made = iter(group.numbers(group.product(np.where(asked, powers, group.one[:, :, None]))))
        for row in weights[at : at + step]:
            used = int(np.count_nonzero(row))
            keys.counts["exponentiations"] += used
            keys.counts["multiplications"] += used
            yield next(made), next(made)


def encrypted_match(probes: DataFrame, gallery: DataFrame, model, variant: str = "interactive", bits: int = 256, scale: int = 64, limit: int = 1024) -> DataFrame:
    """B5 (interactive) and B6 (packed, two distances a ciphertext): id, match, cost counts and seconds per probe.

    Probes are dealt over all tasks; the gallery's scores, at most ``limit`` rows of a few
    integers each, go to all of them.
    """
    rows = gallery.select("id", "px").limit(limit + 1).collect()
    if len(rows) > limit:
        raise ValueError("encrypted matching is for small galleries")
    basis = np.rint(model.vectors * scale).astype(int)
    quantise = lambda x: np.rint(np.asarray(x, np.float64) * scale).astype(int)
    offset = (basis @ quantise(model.mean)).tolist()
    known = {r["id"]: (basis @ quantise(r["px"]) - offset).tolist() for r in rows}
    slots = 2 if variant == "packed" else 1

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keys = Paillier.fresh(bits)
        for batch in batches:
            if not batch.num_rows:
                continue
            out, took = [], []
            for i, x in zip(batch.column("id").to_pylist(), block(batch.column("px"))):
                began = time.perf_counter()
                out.append(match_encrypted(keys, quantise(x).tolist(), known, basis.tolist(), offset, slots, seed=int(i)))
                took.append(time.perf_counter() - began)
            names = ("encryptions", "decryptions", "exponentiations", "multiplications", "rounds")
            yield pa.RecordBatch.from_arrays([batch.column("id"), pa.array([m for m, _ in out], pa.int64()), *(pa.array([c[n] for _, c in out], pa.int64()) for n in names), pa.array(took, pa.float64())], ["id", "match", *names, "seconds"])

    spread = probes.select("id", "px").repartition(probes.sparkSession.sparkContext.defaultParallelism, "id")
    return spread.mapInArrow(run, "id long, match long, encryptions long, decryptions long, exponentiations long, multiplications long, rounds long, seconds double")
