"""Exact deduplication with a heavy-hitter split.

A Misra-Gries summary per task finds digests that may be frequent; summaries are
summed, the leading candidates are counted exactly, and the verified winners are
broadcast (at most ``counters`` rows) so that their rows are decided where they
are read. All other digests are grouped by an ordinary shuffle of narrow rows.

Defined cases: a null text counts as empty, so nulls and empty texts form one
group; equal texts keep the row with the largest id (a null id counts as lowest);
rows of one id are judged each by its own text, and equal rows share a verdict
(``deduplicated`` keeps one of them); further columns are ignored; an empty table
gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.scratch import materialise, small_side
from .rows import ROW_KEY, with_row_key


def misra_gries(counters: int):
    """A ``mapInArrow`` function: (digest) -> at most ``counters`` rows (digest, count) a task.

    Every digest with more than rows / (counters + 1) occurrences in the task is kept.
    """

    def summarise(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept: dict[bytes, int] = {}
        for batch in batches:
            for pair in pc.value_counts(batch.column(0)):
                key = pair["values"].as_py()
                kept[key] = kept.get(key, 0) + pair["counts"].as_py()
            if len(kept) > counters:
                counts = np.fromiter(kept.values(), np.int64, len(kept))
                least = int(np.partition(counts, -(counters + 1))[-(counters + 1)])
                kept = {k: c - least for k, c in kept.items() if c > least}
        yield pa.record_batch({"digest": pa.array(list(kept), pa.binary()), "count": pa.array(list(kept.values()), pa.int64())})

    return summarise


def group_digests(rows: DataFrame, counters: int = 256, pick=F.max) -> DataFrame:
    """``rows`` (id, digest, any others) with the group's ``keep_id`` (the ``pick`` of its ids) and ``group_size``; they must be cheap to read again."""
    summary = rows.select("digest").mapInArrow(misra_gries(counters), "digest binary, count long")
    candidates = summary.groupBy("digest").agg(F.sum("count").alias("count")).orderBy(F.desc("count"), "digest").limit(counters).select("digest")
    exact = [pick("id").alias("keep_id"), F.count(F.lit(1)).alias("group_size")]
    # At most ``counters`` rows, by the limit above.
    hot = materialise(rows.join(F.broadcast(candidates), "digest").groupBy("digest").agg(*exact).where("group_size > 1"), "hot-digests")
    map_side = rows.join(F.broadcast(hot), "digest")
    rest = rows.join(F.broadcast(hot.select("digest")), "digest", "left_anti")
    shuffled = rest.join(rest.groupBy("digest").agg(*exact), "digest")
    cols = [*rows.columns, "keep_id", "group_size"]
    return map_side.select(*cols).unionByName(shuffled.select(*cols))


def exact_dedup(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", normalise=None, counters: int = 256) -> DataFrame:
    """One row per input row: id, ``keep_id``, ``group_size``, ``kept``, ``text_sha256``.

    ``normalise``: a function of the text column, applied before comparison (none: texts must be identical).
    """
    text: Column = F.coalesce(F.col(text_col), F.lit(""))
    digest = F.unhex(F.sha2(normalise(text) if normalise else text, 256))
    rows = materialise(docs.select(F.col(id_col).alias("id"), digest.alias("digest")), "digests")
    return group_digests(rows, counters).select(
        F.col("id").alias(id_col), F.col("keep_id"), F.col("group_size"), F.col("id").eqNullSafe(F.col("keep_id")).alias("kept"), F.lower(F.hex("digest")).alias("text_sha256")
    )


def deduplicated(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", counters: int = 256) -> DataFrame:
    """One row of each text, all columns unchanged: that of the largest id.

    Rows are judged by id and text together, so an id whose rows carry several texts loses only the copies.
    Of rows that are equal in both, one stays (any, if further columns differ).
    """
    digest = F.unhex(F.sha2(F.coalesce(F.col(text_col), F.lit("")), 256))
    keyed = with_row_key(docs, id_col, text_col, lowest=True).withColumn("_digest", digest)
    verdict = exact_dedup(keyed, ROW_KEY, text_col, counters=counters).where("group_size > 1").select(F.col(ROW_KEY), F.unhex("text_sha256").alias("_digest"), "kept")
    verdict = materialise(verdict, "verdict")
    pair = [ROW_KEY, "_digest"]
    dropped = materialise(verdict.where("NOT kept").select(*pair).distinct(), "dropped")
    again = materialise(verdict.where("kept").groupBy(*pair).agg(F.count(F.lit(1)).alias("n")).where("n > 1").select(*pair), "again")
    stay = keyed.join(small_side(dropped), pair, "left_anti")
    repeated = small_side(again)
    return stay.join(repeated, pair, "left_anti").select(*docs.columns).unionByName(stay.join(repeated, pair, "left_semi").dropDuplicates(pair).select(*docs.columns))
