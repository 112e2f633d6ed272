"""Running a block function over the texts of a table, and bounded label samples."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..plans.scratch import hash60, materialise, small_side
from .kernel import blocks

#: Blocks of text whose results are sent back together.
OUT_BLOCKS = 16
#: A function of one block: (byte buffer, offsets) -> an array per new column.
BlockFunction = Callable[[np.ndarray, np.ndarray], dict[str, np.ndarray]]


def with_text_columns(df: DataFrame, text: str, make: Callable[[], BlockFunction], new: dict[str, T.DataType], keep: list[str] | None = None) -> DataFrame:
    """``keep`` (default: all) columns of ``df`` and the ``new`` ones computed from whole texts, row by row and without a shuffle.

    ``make`` is called once in each task. A new column whose name is taken replaces the old one.
    """
    keep = [c for c in (df.columns if keep is None else keep) if c not in new]
    schema = T.StructType([*(df.schema[c] for c in keep), *(T.StructField(n, t) for n, t in new.items())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        function = make()

        def joined(rows: pa.RecordBatch, parts: list[dict]) -> pa.RecordBatch:
            arrays = [rows.column(rows.schema.get_field_index(c)) for c in keep]
            for n in new:
                made = [p[n] for p in parts]
                arrays.append(pa.concat_arrays(made) if isinstance(made[0], pa.Array) else pa.array(np.concatenate(made)))
            return pa.RecordBatch.from_arrays(arrays, names=[*keep, *new])

        for batch in batches:
            parts, start, done = [], 0, 0
            for rows, data, offsets in blocks(iter([batch]), text):
                parts.append(function(data, offsets))
                done += rows.num_rows
                if len(parts) == OUT_BLOCKS:  # bounds what waits to be sent back
                    yield joined(batch.slice(start, done - start), parts)
                    parts, start = [], done
            if parts:
                yield joined(batch.slice(start, done - start), parts)

    return df.select(*dict.fromkeys([*keep, text])).mapInArrow(run, schema)


def fold_of(key: Column, folds: int = 5) -> Column:
    """crc32 of the key's text form, modulo ``folds``; 0 is held out. A null key counts as the empty text."""
    return F.crc32(F.coalesce(key.cast("string"), F.lit("")).cast("binary")) % folds


#: The column of ``with_row_key``.
ROW_KEY = "_row_key"


def with_row_key(df: DataFrame, id_col: str, text_col: str, lowest: bool, distinct_texts: bool = False) -> DataFrame:
    """Adds ROW_KEY: the id, or where it is null a number made of 60 bits of the text's md5, below or above the usual ids.

    So rows without an id are documents by their texts (null counts as empty), and can be joined to their verdicts.
    With ``distinct_texts`` the same holds for rows of an id under which several texts stand, so a key has one text.
    """
    made = (F.lit(1 << 62) + hash60(F.col(text_col))) * F.lit(-1 if lowest else 1)
    text_id = isinstance(df.schema[id_col].dataType, T.StringType)
    made = made.cast("string") if text_id else made
    if not distinct_texts:
        return df.withColumn(ROW_KEY, F.coalesce(F.col(id_col), made))
    marks = df.where(F.col(id_col).isNotNull()).select(F.col(id_col).alias("_id"), hash60(F.col(text_col)).alias("_h"))
    torn = small_side(materialise(marks.groupBy("_id").agg(F.min("_h").alias("a"), F.max("_h").alias("b")).where("a <> b").select("_id"), "torn-ids"))
    joined = df.join(torn, F.col(id_col) == F.col("_id"), "left")
    return joined.withColumn(ROW_KEY, F.when(F.col("_id").isNull(), F.col(id_col)).otherwise(F.lit(None))).withColumn(ROW_KEY, F.coalesce(ROW_KEY, made)).drop("_id")


def label_sample(labels: DataFrame, id_col: str, label_col: str, per_class: int) -> tuple[DataFrame, dict]:
    """About ``per_class`` ids of each label (chosen by the hash of the id) as (id, label, draw), and all rows' counts by label.

    An id with several labels counts once, with the largest. ``draw`` is a second hash, 0 to 99.
    """
    one = labels.where(F.col(label_col).isNotNull() & F.col(id_col).isNotNull()).groupBy(F.col(id_col).alias("id")).agg(F.max(label_col).alias("label"))
    counts = {r["label"]: r["n"] for r in one.groupBy("label").agg(F.count(F.lit(1)).alias("n")).collect()}
    share = F.create_map(*[x for k, n in counts.items() for x in (F.lit(k), F.lit(min(1.0, per_class / n) * float(1 << 60)))]) if counts else F.lit(None)
    chosen = one.where(hash60(F.col("id")).cast("double") <= share[F.col("label")]) if counts else one.limit(0)
    return chosen.select("id", "label", F.pmod(F.xxhash64("id", F.lit(7)), F.lit(100)).cast("int").alias("draw")), counts


def one_text_each(texts: DataFrame) -> DataFrame:
    """Of several rows (id, text, ...) of one id the one whose text is first in byte order, null before all."""
    rest = [c for c in texts.columns if c not in ("id", "text")]
    return texts.groupBy("id").agg(F.min(F.struct("text", *rest)).alias("one")).select("id", "one.*")


def logistic(x: np.ndarray, y: np.ndarray, weight: np.ndarray, l2: float = 1e-2, steps: int = 60) -> np.ndarray:
    """Newton's method for a weighted logistic regression; the last coefficient is the (free) intercept."""
    x = np.column_stack([x, np.ones(len(x))])
    beta, ridge = np.zeros(x.shape[1]), np.diag([l2] * (x.shape[1] - 1) + [1e-6]) * weight.sum()
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(x @ beta, -30, 30)))
        grad = x.T @ (weight * (p - y)) + ridge @ beta
        step = np.linalg.solve((x * (weight * p * (1 - p))[:, None]).T @ x + ridge + 1e-9 * np.eye(len(beta)), grad)
        beta -= step * min(1.0, 5 / (np.abs(step).max() + 1e-12))
        if np.abs(step).max() < 1e-8:
            break
    return beta
