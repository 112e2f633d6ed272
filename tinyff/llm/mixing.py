"""Mixing sources to target weights with hash-threshold histograms.

A document's place in its source's order is 60 bits of the md5 of its id. Sizes
are summed by source and by the next 12 hash bits; the bucket in which a source's
budget runs out is found, and only that bucket is refined by the following bits.
Documents are then taken by comparing their hash with one threshold a source:
nothing is sorted, and thresholds of growing budgets are nested.

Defined cases: a null or empty text has size 0 and is taken 0 times (0 words); a
null source is a source of its own, placed last; a null id hashes as the empty
text; rows with one id share one hash and so one verdict; documents of equal hash
stand or fall together; further columns are ignored; an empty table gives none.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..plans.scratch import hash60, materialise, small_side

BITS, LEVEL_BITS = 60, 12
#: More sources than this are joined by a shuffle instead of a broadcast.
MOST_SOURCES = 100_000


def word_count(text):
    """Maximal runs of anything but blanks; null: 0."""
    return F.coalesce(F.regexp_count(text, F.lit(r"[^\x20\x09-\x0D]+")), F.lit(0)).cast("long")


def _placed(totals: DataFrame) -> DataFrame:
    """Adds ``place``: the rank of each source by code point, null last, without bringing the sources into one task.

    Sources are dealt by ranges; a range's first place is the number of sources in the ranges before it.
    """
    dealt = totals.withColumn("last", F.col("source").isNull()).repartitionByRange("last", "source").withColumn("range", F.spark_partition_id())
    dealt = materialise(dealt, "sources")
    sizes, before = sorted(dealt.groupBy("range").agg(F.count(F.lit(1))).collect()), [F.lit(-1), F.lit(0)]  # one row a range
    for at, (part, _) in enumerate(sizes):
        before += [F.lit(part), F.lit(sum(n for _, n in sizes[:at]))]
    inside = F.row_number().over(Window.partitionBy("range").orderBy("last", "source"))
    return dealt.select("source", "source_size", (F.element_at(F.create_map(*before), F.col("range")) + inside).alias("place"))


def source_targets(sizes: DataFrame, weights: tuple[int, ...], share: float, most: float) -> DataFrame:
    """(source, source_size, target): ``share`` of all words by weight, at most ``most`` times a source's own.

    Weights repeat over the sources in code-point order. Capping some sources raises the rate of the
    others: each round is one aggregate over the sources, and ends when no further source is capped.
    """
    weight = F.array(*[F.lit(w) for w in weights])
    weighed = _placed(sizes.groupBy("source").agg(F.sum("size").alias("source_size")))
    weighed = weighed.withColumn("weight", F.element_at(weight, ((F.col("place") - 1) % len(weights) + 1).cast("int")))
    weighed = materialise(weighed.withColumn("cap", F.lit(float(most)) * F.col("source_size")).withColumn("rate", F.col("cap") / F.col("weight")), "weighed")
    rate, capped = None, -1
    while True:
        below = F.lit(False) if rate is None else F.col("rate") < F.lit(rate)
        total, used, open_weight, n = weighed.agg(F.sum("source_size"), F.sum(F.when(below, F.col("cap"))), F.sum(F.when(~below, F.col("weight"))), F.count_if(below)).first()
        if n == capped or not open_weight:
            break
        rate, capped = (total * float(share) - (used or 0.0)) / open_weight, n
    target = F.col("cap") if rate is None or not open_weight else F.least("cap", F.col("weight") * F.lit(rate))
    return weighed.select("source", "source_size", target.cast("double").alias("target"))


def _boundary(hist: DataFrame, state: DataFrame) -> DataFrame:
    """For each source with an open budget, the first bucket whose words go beyond it."""
    upto = F.sum("words").over(Window.partitionBy("source").orderBy("bucket"))
    run = hist.withColumn("upto", upto).join(state.select(F.col("source").alias("of"), "extra", "before"), F.col("source").eqNullSafe(F.col("of")))
    over = run.where(F.col("before") + F.col("upto") > F.col("extra"))
    return over.groupBy("of", "extra").agg(F.min_by(F.struct("bucket", (F.col("before") + F.col("upto") - F.col("words")).alias("before"), "words"), "bucket").alias("at")).select(
        F.col("of").alias("source"), "extra", F.col("at.bucket").alias("prefix"), F.col("at.before").alias("before"), F.col("at.words").alias("words")
    )


def thresholds(sizes: DataFrame, targets: DataFrame) -> DataFrame:
    """``targets`` with ``passes`` (whole takings of every document) and ``until`` (hashes up to it are taken once more)."""
    passes = F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(0).cast("long")
    plan = targets.withColumn("passes", passes).withColumn("extra", F.col("target") - F.col("passes") * F.col("source_size"))
    state = plan.where("extra > 0").select("source", "extra", F.lit(0).cast("long").alias("prefix"), F.lit(0).cast("long").alias("before"))
    rows = sizes.select("source", "size", "hash")
    for level in range(1, BITS // LEVEL_BITS + 1):
        shift = BITS - level * LEVEL_BITS
        mine = small_side(state.select(F.col("source").alias("of"), "prefix"), MOST_SOURCES) if level > 1 else None
        if level > 1:
            above = F.shiftright("hash", shift + LEVEL_BITS)
            rows = rows.join(mine, F.col("source").eqNullSafe(F.col("of")) & (above == F.col("prefix"))).select("source", "size", "hash")
            if level == 2:  # the boundary buckets alone, about 1/4096 of the rows
                rows = materialise(rows, "boundary")
        hist = rows.groupBy("source", F.shiftright("hash", shift).alias("bucket")).agg(F.sum("size").alias("words"))
        state = materialise(_boundary(hist, state), "budget")
    nearer = 2 * (F.col("extra") - F.col("before")) >= F.col("words")
    cut = state.select(F.col("source").alias("of"), F.when(nearer, F.col("prefix")).otherwise(F.col("prefix") - 1).alias("cut"))
    every = F.when(F.col("extra") > 0, F.lit((1 << BITS) - 1)).otherwise(-1).cast("long")
    return plan.join(cut, F.col("source").eqNullSafe(F.col("of")), "left").select("source", "source_size", "target", "passes", F.coalesce("cut", every).alias("until"))


def _planned(docs: DataFrame, id_col: str, text_col: str, source_col: str, weights: tuple[int, ...], share: float, most: float) -> tuple[DataFrame, DataFrame]:
    """The narrow rows of ``docs``, and the plan of each source (named ``of``) with a broadcast hint."""
    key = hash60(F.col(id_col))
    sizes = materialise(docs.select(F.col(id_col).alias("id"), F.col(source_col).alias("source"), word_count(F.col(text_col)).alias("size"), key.alias("hash")), "sizes")
    targets = materialise(source_targets(sizes, weights, share, most), "targets")
    return sizes, small_side(materialise(thresholds(sizes, targets), "thresholds").withColumnRenamed("source", "of"), MOST_SOURCES)


def mix(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", weights: tuple[int, ...] = (3, 1, 2), share: float = 1.5, most: float = 2.0) -> DataFrame:
    """One row per input row: id, ``size``, ``source_size``, ``target`` (its source's), ``taken`` (words, repeats counted), ``copies``."""
    sizes, plan = _planned(docs, id_col, text_col, source_col, weights, share, most)
    copies = F.when(F.col("size") > 0, F.col("passes") + (F.col("hash") <= F.col("until")).cast("long")).otherwise(0).cast("long")
    joined = sizes.join(plan, F.col("source").eqNullSafe(F.col("of")))
    return joined.select(F.col("id").alias(id_col), "size", "source_size", "target", (F.col("size") * copies).alias("taken"), copies.alias("copies"))


def mixed(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", weights: tuple[int, ...] = (3, 1, 2), share: float = 1.5, most: float = 2.0) -> DataFrame:
    """The mix itself: each row of ``docs`` as often as ``mix`` takes it, numbered by ``copy`` from 1. Rows meet their source's plan, so ids may be null."""
    _, plan = _planned(docs, id_col, text_col, source_col, weights, share, most)
    plan = plan.select(F.col("of").alias("_mix_of"), F.struct("passes", "until").alias("_mix"))
    words = F.coalesce(F.regexp_like(text_col, F.lit(r"[^\x20\x09-\x0D]")), F.lit(False))
    copies = F.when(words, F.col("_mix.passes") + (hash60(F.col(id_col)) <= F.col("_mix.until")).cast("long")).otherwise(0)
    name = "copy" if "copy" not in docs.columns else "mix_copy"
    out = docs.join(plan, F.col(source_col).eqNullSafe(F.col("_mix_of"))).withColumn("_mix_copies", copies).where("_mix_copies > 0")
    return out.withColumn(name, F.explode(F.sequence(F.lit(1), F.col("_mix_copies").cast("int")))).select(*docs.columns, name)
