"""Quality measures over (gold, predicted) columns and over orders."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def confusion(df: DataFrame, gold: str, pred: str) -> DataFrame:
    return df.groupBy(F.col(gold).alias("gold"), F.col(pred).alias("pred")).agg(F.count(F.lit(1)).alias("n"))


def per_class(df: DataFrame, gold: str, pred: str) -> DataFrame:
    """(label, tp, fp, fn, precision, recall, f1) from a table of at most classes squared rows."""
    c = confusion(df, gold, pred)
    hit = F.when(F.col("gold") == F.col("pred"), F.col("n")).otherwise(0)
    as_pred = c.groupBy(F.col("pred").alias("label")).agg(F.sum(hit).alias("tp"), F.sum(F.col("n") - hit).alias("fp"))
    as_gold = c.groupBy(F.col("gold").alias("label")).agg(F.sum(F.col("n") - hit).alias("fn"))
    both = as_pred.join(as_gold, "label", "full").na.fill(0, ["tp", "fp", "fn"])
    ratio = lambda a, b: F.when(b > 0, a / b).otherwise(F.lit(0.0))
    tp, fp, fn = F.col("tp"), F.col("fp"), F.col("fn")
    return both.select("label", "tp", "fp", "fn", ratio(tp, tp + fp).alias("precision"), ratio(tp, tp + fn).alias("recall"), ratio(2 * tp, 2 * tp + fp + fn).alias("f1"))


def micro_f1(df: DataFrame, gold: str, pred: str) -> DataFrame:
    return per_class(df, gold, pred).agg((F.sum("tp") / (F.sum("tp") + (F.sum("fp") + F.sum("fn")) / 2)).alias("micro_f1"))


def macro_f1(df: DataFrame, gold: str, pred: str) -> DataFrame:
    return per_class(df, gold, pred).agg(F.avg("f1").alias("macro_f1"))


def accuracy(df: DataFrame, gold: str, pred: str, by: str | None = None) -> DataFrame:
    right = F.avg((F.col(gold) == F.col(pred)).cast("double")).alias("accuracy")
    return (df.groupBy(by) if by else df.groupBy()).agg(F.count(F.lit(1)).alias("n"), right)


def inversions(perm: Column) -> Column:
    """Pairs of an order that stand the wrong way round."""
    n = F.size(perm)
    later = lambda i: F.size(F.filter(F.slice(perm, i + 1, n), lambda x: x < F.element_at(perm, i)))
    return F.when(n > 1, F.aggregate(F.sequence(F.lit(1), n), F.lit(0), lambda a, i: a + later(i))).otherwise(0)


def kendall(perm: Column) -> Column:
    n = F.size(perm)
    return F.when(n > 1, 1 - 2 * inversions(perm) / (n * (n - 1) / 2)).otherwise(F.lit(1.0))


def frs_pairs(perm: Column) -> Column:
    """Share of neighbouring pairs kept, both ends included: ``perm`` gives target ranks 0 .. n-1 in the produced order."""
    n = F.size(perm)
    full = F.concat(F.array(F.lit(-1)), perm, F.array(n))
    kept = F.aggregate(F.sequence(F.lit(1), n + 1), F.lit(0), lambda a, i: a + F.when(F.element_at(full, i + 1) == F.element_at(full, i) + 1, 1).otherwise(0))
    return 100.0 * kept / (n + 1)


def frs_chunks(perm: Column) -> Column:
    """One minus the number of breaks between unbroken chunks over the largest possible number."""
    n = F.size(perm)
    breaks = F.aggregate(F.sequence(F.lit(1), F.greatest(n - 1, F.lit(1))), F.lit(0), lambda a, i: a + F.when((i < n) & (F.element_at(perm, F.least(i + 1, n)) != F.element_at(perm, i) + 1), 1).otherwise(0))
    return F.when(n > 1, 100.0 * (1 - breaks / (n - 1))).otherwise(F.lit(100.0))


def rel_error_reduction(before: float, after: float) -> float:
    return (after - before) / (100 - before)


def word_prf(gold_spans: set, pred_spans: set) -> tuple[int, int, int]:
    return len(gold_spans & pred_spans), len(pred_spans), len(gold_spans)
