"""Vector arithmetic and keyed noise as built-in expressions: no Python on the executors.

Every draw is a function of (key, release, record, index), so a task that runs again
publishes the same noise.  The md5 form is for tests and oracles; ``secret=True`` takes
sha2-256 of the same text with a secret key.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def _col(x) -> Column:
    return x if isinstance(x, Column) else F.col(x)


def vec_sub(a, b) -> Column:
    return F.zip_with(_col(a), _col(b), lambda x, y: x - y)


def vec_add(a, b) -> Column:
    return F.zip_with(_col(a), _col(b), lambda x, y: x + y)


def _total(values: Column) -> Column:
    return F.aggregate(values, F.lit(0.0), lambda s, v: s + v)


def vec_dot(a, b) -> Column:
    return _total(F.zip_with(_col(a), _col(b), lambda x, y: x.cast("double") * y.cast("double")))


def vec_l1(a, b) -> Column:
    return _total(F.zip_with(_col(a), _col(b), lambda x, y: F.abs(x.cast("double") - y.cast("double"))))


def vec_l2(a, b) -> Column:
    return F.sqrt(_total(F.zip_with(_col(a), _col(b), lambda x, y: (x.cast("double") - y.cast("double")) * (x.cast("double") - y.cast("double")))))


def vec_scale01(v, lo, hi, clip: bool = True) -> Column:
    """Min-max scaling per index; a constant index becomes 0.5."""

    def one(x, pair):
        got = F.when(pair["hi"] > pair["lo"], (x - pair["lo"]) / (pair["hi"] - pair["lo"])).otherwise(F.lit(0.5))
        return F.greatest(F.lit(0.0), F.least(F.lit(1.0), got)) if clip else got

    pairs = F.zip_with(_col(lo), _col(hi), lambda a, b: F.struct(a.alias("lo"), b.alias("hi")))
    return F.zip_with(_col(v), pairs, one)


def keyed_uniform(*parts, secret: bool = False) -> Column:
    """A number in (0, 1) from the parts joined by bars: 48 bits of their digest, centred."""
    text = F.concat_ws("|", *[p if isinstance(p, Column) else F.lit(str(p)) for p in parts])
    digest = F.sha2(text, 256) if secret else F.md5(text)
    return (F.conv(F.substring(digest, 1, 12), 16, 10).cast("double") + F.lit(0.5)) / F.lit(float(1 << 48))


def laplace_icdf(u: Column, scale) -> Column:
    scale = scale if isinstance(scale, Column) else F.lit(float(scale))
    return -scale * F.signum(u - 0.5) * F.log(F.lit(1.0) - 2.0 * F.abs(u - 0.5))


def laplace_pdf(x: Column, at: Column, eps: float, delta: float = 1.0) -> Column:
    return F.lit(eps / (2 * delta)) * F.exp(-F.abs(x - at) * F.lit(eps / delta))


def laplace_cdf(x: Column, at: Column, eps: float, delta: float = 1.0) -> Column:
    tail = F.exp(-F.abs(x - at) * F.lit(eps / delta)) / 2.0
    return F.when(x < at, tail).otherwise(F.lit(1.0) - tail)


def gaussian_draw(u1: Column, u2: Column, sigma: float) -> Column:
    """Box-Muller."""
    return F.lit(sigma) * F.sqrt(-2.0 * F.log(u1)) * F.cos(F.lit(6.283185307179586) * u2)


def perturb(v, eps: float, delta: float, key: str, record, release: str = "r1", secret: bool = False, snap: float | None = None) -> Column:
    """Each index plus Laplace noise of scale delta / eps; ``snap`` rounds to a grid."""
    record = _col(record)

    def one(x, i):
        y = x.cast("double") + laplace_icdf(keyed_uniform(key, release, record.cast("string"), i.cast("string"), secret=secret), delta / eps)
        return F.round(y / snap) * snap if snap else y

    return F.transform(_col(v), one)
