"""Sensitivity, the Laplace and Gaussian mechanisms."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import gaussian_draw, keyed_uniform, perturb
from ..params import check_budget


def sensitivity(nc: int, mode: str = "index") -> float:
    """One index (1), Euclidean (root of nc) or L1 (nc), for vectors in [0, 1]."""
    return {"index": 1.0, "euclidean": math.sqrt(nc), "l1": float(nc)}[mode]


def empirical_sensitivity_bound(df: DataFrame, column: str = "score", norm: int = 1) -> float:
    """M20a at scale: the norm of the per-index ranges, which no pair of records exceeds."""
    from .scaling import fit_bounds

    bounds = fit_bounds(df, column)
    ranges = bounds.hi - bounds.lo
    return float(ranges.sum() if norm == 1 else math.sqrt((ranges**2).sum()))


def laplace(df: DataFrame, column: str, eps: float | None, delta: float, key: str, id_: str = "id", release: str = "r1", out: str | None = None, allow_extreme: bool = False, secret: bool = False, snap: float | None = None) -> DataFrame:
    """Adds Laplace noise of scale delta / eps to each index; no noise without a budget."""
    eps = check_budget(eps, allow_extreme=allow_extreme)
    if eps is None:
        return df.withColumn(out or column, F.col(column))
    return df.withColumn(out or column, perturb(column, eps, delta, key, id_, release, secret=secret, snap=snap))


def gaussian_sigma(eps: float, delta_p: float, l2: float) -> float:
    """The classic bound below budget 1; above it the least sigma of the analytic condition."""
    if eps < 1:
        return l2 * math.sqrt(2 * math.log(1.25 / delta_p)) / eps

    def spent(sigma: float) -> float:
        a, b = l2 / (2 * sigma), eps * sigma / l2
        phi = lambda t: 0.5 * math.erfc(-t / math.sqrt(2))
        return phi(a - b) - math.exp(eps) * phi(-a - b)

    lo, hi = 1e-6 * l2, 1e3 * l2
    for _ in range(200):
        mid = (lo + hi) / 2
        lo, hi = (lo, mid) if spent(mid) <= delta_p else (mid, hi)
    return hi


def gaussian(df: DataFrame, column: str, eps: float, delta_p: float, l2: float, key: str, id_: str = "id", release: str = "g1", out: str | None = None) -> DataFrame:
    """Gaussian noise by Box-Muller from two keyed uniforms per index."""
    sigma = gaussian_sigma(eps, delta_p, l2)

    def one(x: Column, i: Column) -> Column:
        u = [keyed_uniform(key, release, F.col(id_).cast("string"), i.cast("string"), F.lit(k)) for k in ("a", "b")]
        return x.cast("double") + gaussian_draw(*u, sigma)

    return df.withColumn(out or column, F.transform(column, one))


def laplace_numpy(u: np.ndarray, scale: float) -> np.ndarray:
    """The same inverse distribution for arrays."""
    return -scale * np.sign(u - 0.5) * np.log(1 - 2 * np.abs(u - 0.5))
