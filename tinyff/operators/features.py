"""Feature groups, templates and vocabularies."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


@dataclass(frozen=True)
class FeatureGroup:
    """One embedding matrix: ``vocab`` rows of ``dim`` numbers, used by ``slots`` places of the input.

    ``n`` is the n-gram length, ``offset`` the first place relative to the focus; ``combine`` says how
    several features of one slot become one vector (mean, sum) or stay side by side (concat).
    """

    name: str
    vocab: int
    dim: int
    slots: int = 1
    n: int = 1
    offset: int = 0
    combine: str = "mean"
    kind: str = "chars"

    @property
    def width(self) -> int:
        return self.dim * self.slots


@dataclass(frozen=True)
class Template:
    groups: tuple[FeatureGroup, ...]

    @property
    def h0(self) -> int:
        return sum(g.width for g in self.groups)


def build_vocab(df: DataFrame, column: str, min_count: int = 2, max_size: int | None = None) -> DataFrame:
    """(value, freq, id) of frequent values, by frequency then value; id 0 is the unknown value and is not listed."""
    counts = df.groupBy(F.col(column).alias("value")).agg(F.count(F.lit(1)).alias("freq")).where(F.col("freq") >= min_count)
    # The order is over distinct values only; a top-k first keeps it small where a size is given.
    ranked = counts.orderBy(F.desc("freq"), "value").limit(max_size) if max_size else counts
    return ranked.withColumn("id", F.row_number().over(Window.orderBy(F.desc("freq"), "value")).cast("long"))
