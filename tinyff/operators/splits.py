"""Deterministic splits, twin removal and bounded samples."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def hash_percent(key: Column) -> Column:
    return F.pmod(F.conv(F.substring(F.md5(key.cast("string")), 1, 8), 16, 10).cast("long"), F.lit(100)).cast("long")


def assign(df: DataFrame, key: str, train: int = 80, dev: int = 10) -> DataFrame:
    """Adds ``part``: train, dev or test by the hash of the key."""
    p = hash_percent(F.col(key))
    return df.withColumn("part", F.when(p < train, "train").when(p < train + dev, "dev").otherwise("test"))


def drop_twins(df: DataFrame, text: str = "text") -> DataFrame:
    """Drops dev and test rows whose exact text occurs in train; only text digests are shuffled."""
    mark = F.md5(text)
    train = df.where(F.col("part") == "train").select(mark.alias("_twin")).distinct()
    rest = df.where(F.col("part") != "train")
    return df.where(F.col("part") == "train").unionByName(rest.join(train, mark == F.col("_twin"), "left_anti"))


def stratified(df: DataFrame, label: str, key: str, per_class: int) -> DataFrame:
    """At most ``per_class`` rows of each label, by the hash of the key: a sampling operator.

    Each task's rows compete for their label's places before the shuffle (a window group limit).
    """
    order = Window.partitionBy(label).orderBy(F.md5(F.col(key).cast("string")), key)
    return df.withColumn("_place", F.row_number().over(order)).where(F.col("_place") <= per_class).drop("_place")
