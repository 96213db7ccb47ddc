"""Checks of the mechanism itself."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import laplace_cdf, laplace_pdf


def noise_moments(draws: DataFrame, column: str = "z") -> DataFrame:
    """Q11: mean, mean absolute value, variance and number of the draws."""
    return draws.agg(F.avg(column).alias("mean"), F.avg(F.abs(column)).alias("mean_abs"), F.var_samp(column).alias("variance"), F.count(column).alias("n"))


def ks_laplace(draws: DataFrame, eps: float, delta: float = 1.0, column: str = "z", bins: int = 256) -> DataFrame:
    """Q11: the greatest distance of the empirical and the Laplace distribution function.

    Ranks are made from counts of ``bins`` quantile ranges plus ranks within each, so no
    task sorts all draws.
    """
    u = laplace_cdf(F.col(column), F.lit(0.0), eps, delta)
    placed = draws.select(u.alias("u")).withColumn("bin", F.least(F.lit(bins - 1), F.floor(F.col("u") * bins)).cast("int"))
    counts = placed.groupBy("bin").agg(F.count("*").alias("n"))
    before = counts.select("bin", (F.sum("n").over(Window.orderBy("bin")) - F.col("n")).alias("before"), F.sum("n").over(Window.partitionBy()).alias("total"))
    ranked = placed.withColumn("k", F.row_number().over(Window.partitionBy("bin").orderBy("u"))).join(F.broadcast(before), "bin")
    high = (F.col("before") + F.col("k")) / F.col("total") - F.col("u")
    low = F.col("u") - (F.col("before") + F.col("k") - 1) / F.col("total")
    return ranked.agg(F.max(F.greatest(high, low)).alias("ks"), F.max("total").alias("n"))


def ldp_ratio(spark: SparkSession, eps: float, delta: float, pairs: list[tuple[float, float]], steps: int = 200, grid: DataFrame | None = None) -> DataFrame:
    """For pairs of inputs the greatest log ratio of densities over ``grid(x)`` (or even steps), and its bound."""
    if grid is None:
        grid = spark.range(steps + 1).select((F.col("id") / F.lit(steps) * 6.0 - 3.0).alias("x"))
    given = spark.createDataFrame(pairs, "v1 double, v2 double")
    both = grid.crossJoin(F.broadcast(given))
    ratio = F.abs(F.log(laplace_pdf(F.col("x"), F.col("v1"), eps, delta)) - F.log(laplace_pdf(F.col("x"), F.col("v2"), eps, delta)))
    return both.groupBy("v1", "v2").agg(F.max(ratio).alias("ratio")).withColumn("bound", F.lit(eps / delta) * F.abs(F.col("v1") - F.col("v2"))).withColumn("holds", F.col("ratio") <= F.col("bound") + 1e-9)


def gdp_ratio(spark: SparkSession, eps: float, n: int, pairs: list[tuple[float, float]], steps: int = 200, grid: DataFrame | None = None) -> DataFrame:
    """The same for a released mean of n values in [0, 1] when one person's value changes.

    The mean moves by |v1 - v2| / n, and its noise has scale 1 / (n * eps).
    """
    return ldp_ratio(spark, eps * n, 1.0, [(a / n, b / n) for a, b in pairs], steps, grid)
