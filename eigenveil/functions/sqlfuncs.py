"""SQL functions with inlined bodies, so the optimiser sees plain expressions."""

from __future__ import annotations

from pyspark.sql import SparkSession

_V = "ARRAY<DOUBLE>"
_FUNCTIONS = {
    "vec_dot": (f"a {_V}, b {_V}", "DOUBLE", "aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, v) -> s + v)"),
    "vec_l1": (f"a {_V}, b {_V}", "DOUBLE", "aggregate(zip_with(a, b, (x, y) -> abs(x - y)), 0D, (s, v) -> s + v)"),
    "vec_l2": (f"a {_V}, b {_V}", "DOUBLE", "sqrt(aggregate(zip_with(a, b, (x, y) -> (x - y) * (x - y)), 0D, (s, v) -> s + v))"),
    "vec_sub": (f"a {_V}, b {_V}", _V, "zip_with(a, b, (x, y) -> x - y)"),
    "vec_scale01": (f"v {_V}, lo {_V}, hi {_V}", _V, "transform(v, (x, i) -> CASE WHEN hi[i] > lo[i] THEN greatest(0D, least(1D, (x - lo[i]) / (hi[i] - lo[i]))) ELSE 0.5D END)"),
    "keyed_uniform": ("k STRING, id STRING, idx STRING", "DOUBLE", "(CAST(conv(substr(md5(concat_ws('|', k, id, idx)), 1, 12), 16, 10) AS DOUBLE) + 0.5D) / 281474976710656D"),
    "laplace_icdf": ("u DOUBLE, b DOUBLE", "DOUBLE", "-b * signum(u - 0.5D) * ln(1D - 2D * abs(u - 0.5D))"),
    "laplace_pdf": ("x DOUBLE, m DOUBLE, b DOUBLE", "DOUBLE", "exp(-abs(x - m) / b) / (2D * b)"),
    "perturb": (
        f"v {_V}, eps DOUBLE, delta DOUBLE, k STRING, id STRING",
        _V,
        "transform(v, (x, i) -> x - (delta / eps) * signum((CAST(conv(substr(md5(concat_ws('|', k, id, CAST(i AS STRING))), 1, 12), 16, 10) AS DOUBLE) + 0.5D) / 281474976710656D - 0.5D)"
        " * ln(1D - 2D * abs((CAST(conv(substr(md5(concat_ws('|', k, id, CAST(i AS STRING))), 1, 12), 16, 10) AS DOUBLE) + 0.5D) / 281474976710656D - 0.5D)))",
    ),
}


def explode_pixels():
    """A table function: (idx, value) of a vector, for use in SQL as ``LATERAL explode_pixels(v)``."""
    from pyspark.sql.functions import udtf

    class ExplodePixels:
        def eval(self, v: list):
            for i, x in enumerate(v or ()):
                yield i, float(x)

    return udtf(ExplodePixels, returnType="idx: bigint, value: double")


def mean_vector():
    """An aggregate: the mean of a group's vectors; exact sums per Arrow group."""
    import numpy as np
    import pandas as pd
    from pyspark.sql.functions import pandas_udf

    def mean(v: pd.Series) -> list:
        return np.mean(np.stack(v.to_list()).astype(np.float64), 0).tolist()

    mean.__annotations__ = {"v": pd.Series, "return": list}
    return pandas_udf(mean, "array<double>")


def register(spark: SparkSession) -> list[str]:
    """Create the temporary functions in this session; their names."""
    for name, (given, kind, body) in _FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({given}) RETURNS {kind} RETURN {body}")
    spark.udtf.register("explode_pixels", explode_pixels())
    return [*_FUNCTIONS, "explode_pixels"]
