"""Which persons and records take part: thresholds, caps and the split."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import keyed_uniform


def keep_frequent(df: DataFrame, imthresh: int, label: str = "label") -> DataFrame:
    """M6: persons with at least ``imthresh`` images.  The counts are one row per person."""
    names = df.groupBy(label).count().where(F.col("count") >= imthresh).select(label)
    return df.join(names, label, "left_semi")


def cap_per_class(df: DataFrame, imthresh: int, label: str = "label", id_: str = "id", mode: str = "at_most", salt: str = "cap", parts: int = 32) -> DataFrame:
    """At most (or exactly, dropping smaller persons) ``imthresh`` images per person.

    The images are those with the least keyed hash; a first ranking within hashed parts
    of a person keeps a frequent person out of a single task.
    """
    order = F.md5(F.concat_ws("|", F.lit(salt), F.col(id_).cast("string")))
    ranked = df.withColumn("__o", order).withColumn("__p", F.pmod(F.xxhash64(id_), F.lit(parts)))
    first = Window.partitionBy(label, "__p").orderBy("__o", id_)
    second = Window.partitionBy(label).orderBy("__o", id_)
    kept = ranked.withColumn("__n", F.row_number().over(first)).where(F.col("__n") <= imthresh).withColumn("__n", F.row_number().over(second)).where(F.col("__n") <= imthresh)
    if mode == "exact":
        full = kept.groupBy(label).agg(F.max("__n").alias("__m")).where(F.col("__m") == imthresh).select(label)
        kept = kept.join(full, label, "left_semi")
    return kept.drop("__o", "__p", "__n")


def split(df: DataFrame, train: float = 0.7, salt: str = "split", id_: str = "id", stratify: str | None = None) -> DataFrame:
    """M7: adds ``split`` (train or test) by a keyed uniform of the id, per person if stratified."""
    u = keyed_uniform(salt, F.col(id_).cast("string"))
    if stratify is None:
        return df.withColumn("split", F.when(u < train, "train").otherwise("test"))
    w = Window.partitionBy(stratify)
    place = F.row_number().over(w.orderBy("__u", id_))
    return df.withColumn("__u", u).withColumn("split", F.when(place <= F.round(train * F.count("*").over(w)), "train").otherwise("test")).drop("__u")
