"""The forward pass as three physical strategies.

relational  n-gram counts, broadcast join with the embedding table, aggregation: SQL's form; counts are made by
            the vector kernel's hashing, and one row a text and group is shuffled
inrow       nested lambdas inside the row: no shuffle, no Python
vector      NumPy over Arrow batches with a broadcast model: the form for large inputs
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import Block, Md5Buckets, bucket
from ..functions.text import bound, char_windows
from .model import AnalyticModel


def gram_counts(df: DataFrame, key: str, text: str, model: AnalyticModel) -> DataFrame:
    """(key, grp, v, cnt): hashed n-grams of all lengths, counted where a text is; rows of one key are not added up."""
    size = max(model.vocab)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        buckets = [Md5Buckets(n, v) for n, v in zip(model.orders, model.vocab, strict=True)]
        for keys, texts in _key_blocks(batches):
            block = Block(texts)
            for g, n in enumerate(model.orders):
                cell, cnt = np.unique(np.repeat(np.arange(len(texts)), block.counts(n)) * size + buckets[g](block), return_counts=True)
                cut = pa.array(np.searchsorted(cell, np.arange(len(texts) + 1) * size).astype(np.int32))
                lists = [pa.ListArray.from_arrays(cut, pa.array(x)) for x in ((cell % size).astype(np.int32), cnt.astype(np.int64))]
                yield pa.RecordBatch.from_arrays([keys, pa.array(np.full(len(texts), g, np.int32)), *lists], names=[key, "grp", "at", "many"])

    made = df.select(key, text).mapInArrow(run, f"{key} {df.schema[key].dataType.simpleString()}, grp int, at array<int>, many array<long>")
    return made.select(key, "grp", F.inline(F.arrays_zip(F.col("at").alias("v"), F.col("many").alias("cnt"))))


def group_sums(df: DataFrame, key: str, text: str, model: AnalyticModel) -> DataFrame:
    """(key, grp, total, s0..): n-grams and summed embeddings of each key and group, by the vector kernel; a group without n-grams has no row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums = _sums(model)
        for keys, texts in _key_blocks(batches):
            total, many = sums(texts)
            for g in range(len(model.orders)):
                has = pa.array(many[:, g] > 0)
                arrays = [keys, pa.array(np.full(len(texts), g, np.int32)), pa.array(many[:, g]), *(pa.array(total[:, g, d]) for d in range(model.dim))]
                yield pa.RecordBatch.from_arrays(arrays, names=[key, "grp", "n", *(f"w{d}" for d in range(model.dim))]).filter(has)

    cells = ", ".join(f"w{d} long" for d in range(model.dim))
    made = df.select(key, text).mapInArrow(run, f"{key} {df.schema[key].dataType.simpleString()}, grp int, n long, {cells}")
    return made.groupBy(key, "grp").agg(F.sum("n").alias("total"), *[F.sum(f"w{d}").alias(f"s{d}") for d in range(model.dim)])


def embed(counts: DataFrame, key: str, model: AnalyticModel, combine: str = "mean") -> DataFrame:
    """(key, grp, e0..): one vector per group, in 1/1024 (mean) or eighths (sum)."""
    table = F.broadcast(model.embedding_table(counts.sparkSession))  # bounded by the vocabulary sizes
    sums = [F.sum(F.col("cnt") * F.col("w")[d]).alias(f"s{d}") for d in range(model.dim)]
    return combined(counts.join(table, ["grp", "v"]).groupBy(key, "grp").agg(F.sum("cnt").alias("total"), *sums), key, model, combine)


def combined(out: DataFrame, key: str, model: AnalyticModel, combine: str = "mean") -> DataFrame:
    """(key, grp, e0..) of the sums of each key and group."""
    if combine == "mean":
        value = lambda d: F.floor(F.lit(128.0) * F.col(f"s{d}") / F.col("total"))
    else:
        value = lambda d: F.col(f"s{d}")
    return out.select(key, "grp", *[value(d).cast("long").alias(f"e{d}") for d in range(model.dim)])


def concat_groups(embedded: DataFrame, keys: DataFrame, key: str, model: AnalyticModel) -> DataFrame:
    """(key, h0): the groups' vectors side by side in template order; an empty group is zero."""
    cells = [F.coalesce(F.max(F.when(F.col("grp") == g, F.col(f"e{d}"))), F.lit(0)).cast("long") for g in range(len(model.orders)) for d in range(model.dim)]
    made = embedded.groupBy(key).agg(F.array(*cells).alias("h0"))
    zero = F.array_repeat(F.lit(0).cast("long"), model.h0)
    return keys.select(key).join(made, key, "left").select(key, F.coalesce("h0", zero).alias("h0"))


def _dot(weights: list[int], vector: Column) -> Column:
    terms = [F.lit(w) * vector[i] for i, w in enumerate(weights) if w]
    return reduce(lambda a, b: a + b, terms) if terms else F.lit(0)


def hidden(h0: Column, model: AnalyticModel) -> Column:
    return F.array(*[F.greatest(F.lit(0).cast("long"), (_dot([model.hidden_weight(j, i) for i in range(model.h0)], h0) + F.lit(model.hidden_bias(j) * 16)).cast("long")) for j in range(model.hidden)])


def logits(h1: Column, model: AnalyticModel) -> Column:
    return F.array(*[(_dot([model.output_weight(y, j) for j in range(model.hidden)], h1) + F.lit(0)).cast("long") for y in range(len(model.classes))])


def argmax_label(z: Column, model: AnalyticModel) -> Column:
    """The largest logit's class; ties go to the first class."""
    return F.element_at(F.array(*map(F.lit, model.classes)), F.array_position(z, F.array_max(z)).cast("int"))


def probabilities(z: Column, scale: float = 1.0) -> Column:
    e = bound(F.array_max(z), lambda top: F.transform(z, lambda x: F.exp((x - top) / scale)))
    return bound(e, lambda e: bound(F.aggregate(e, F.lit(0.0), lambda a, b: a + b), lambda total: F.transform(e, lambda x: x / total)))


def in_row_h0(text: Column, model: AnalyticModel) -> Column:
    """h0 of one text by lambdas only; a bucket's weights are computed, not looked up.

    Windows of the longest n-gram are sorted once, so n-grams of each length are runs of equal beginnings: a distinct
    one is hashed once in a row and weighs as often as it occurs.
    """
    longest, none = max(model.orders), F.array().cast("array<int>")

    def runs(s: Column, at: Column, n: int) -> Column:
        """Those of the places ``at`` where windows begin with another n-gram than the one before."""
        head = lambda i: F.get(s, i) if n == longest else F.substring(F.get(s, i), 1, n)
        return F.filter(at, lambda i: (i == 0) | (head(i) != head(i - 1)))

    def group(s: Column, at: Column, g: int, n: int, size: int) -> Column:
        many = F.size(s) - (n - 1)
        times = lambda i, k: F.when(F.length(F.get(s, i)) >= n, F.coalesce(F.get(at, k + 1), F.size(s)) - i).otherwise(0).cast("long")
        cells = F.transform(at, lambda i, k: F.struct(bucket(F.substring(F.get(s, i), 1, n), size, "md5").alias("v"), times(i, k).alias("cnt")))
        total = lambda x, d: F.aggregate(x, F.lit(0).cast("long"), lambda a, e: a + e["cnt"] * model.embedding(g, e["v"], d))
        mean = lambda x, d: F.floor(F.lit(128.0) * total(x, d) / many).cast("long")
        return bound(cells, lambda x: F.array(*[F.when(many > 0, mean(x, d)).otherwise(F.lit(0).cast("long")) for d in range(model.dim)]))

    def nested(s: Column, at: Column, left: list[int], found: dict[int, Column]) -> Column:
        """Runs of a shorter n-gram are sought among those of the longer ones."""
        if left:
            return bound(runs(s, at, left[0]), lambda x: nested(s, x, left[1:], found | {left[0]: x}))
        return F.concat(*[group(s, found[n], g, n, size) for g, (n, size) in enumerate(zip(model.orders, model.vocab, strict=True))])

    places = lambda s: F.when(F.size(s) > 0, F.sequence(F.lit(0), F.size(s) - 1)).otherwise(none)
    return bound(F.sort_array(char_windows(text, longest)), lambda s: nested(s, places(s), sorted(set(model.orders), reverse=True), {}))


#: Characters of texts that are scored together.
BLOCK_CHARS = 1 << 18


def text_blocks(texts: list[str], most: int = BLOCK_CHARS) -> Iterator[tuple[int, int]]:
    """Ranges of texts of about ``most`` characters together."""
    start, size = 0, 0
    for i, t in enumerate(texts):
        if size and size + len(t) > most:
            yield start, i
            start, size = i, 0
        size += len(t)
    if start < len(texts):
        yield start, len(texts)


def _key_blocks(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[pa.Array, list[str]]]:
    """Keys and lower-cased texts (the second column) of about BLOCK_CHARS characters together."""
    for batch in batches:
        texts = [(t or "").lower() for t in batch.column(1).to_pylist()]
        for a, b in text_blocks(texts):
            yield batch.column(0).slice(a, b - a), texts[a:b]


def _sums(model: AnalyticModel):
    """A function of texts: summed embeddings (text, group, dimension) and n-grams (text, group)."""
    tables = [np.array([[model.embedding(g, v, d) for d in range(model.dim)] for v in range(size)], np.int64) for g, size in enumerate(model.vocab)]
    buckets = [Md5Buckets(n, size) for n, size in zip(model.orders, model.vocab, strict=True)]

    def run(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        block = Block(texts)
        total, many = np.zeros((len(texts), len(model.orders), model.dim), np.int64), np.zeros((len(texts), len(model.orders)), np.int64)
        for g, n in enumerate(model.orders):
            many[:, g] = block.counts(n)
            end = np.cumsum(many[:, g])
            run_total = np.vstack([np.zeros((1, model.dim), np.int64), np.cumsum(tables[g][buckets[g](block)], 0)])
            total[:, g] = run_total[end] - run_total[end - many[:, g]]
        return total, many

    return run


def _vector_predict(model: AnalyticModel, key: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums = _sums(model)
        w = np.array([[model.hidden_weight(j, i) for i in range(model.h0)] for j in range(model.hidden)], np.int64)
        c = np.array([model.hidden_bias(j) * 16 for j in range(model.hidden)], np.int64)
        beta = np.array([[model.output_weight(y, j) for j in range(model.hidden)] for y in range(len(model.classes))], np.int64)
        for keys, texts in _key_blocks(batches):
            total, many = sums(texts)
            h0 = np.floor(128.0 * total / np.maximum(many, 1)[:, :, None]).astype(np.int64).reshape(len(texts), model.h0)
            z = np.maximum(h0 @ w.T + c, 0) @ beta.T
            yield pa.record_batch({key: keys, "label": pa.array(np.array(model.classes, object)[z.argmax(1)], pa.string()), "score": pa.array(z.max(1))})

    return run


def predict(df: DataFrame, model: AnalyticModel, key: str, text: str = "text", strategy: str = "vector") -> DataFrame:
    """(key, label, score) of every row of distinct keys; all strategies give the same."""
    rows = df.select(key, F.col(text).alias("text"))
    if strategy == "vector":
        return rows.mapInArrow(_vector_predict(model, key), f"{key} {df.schema[key].dataType.simpleString()}, label string, score long")
    if strategy == "relational":
        h = concat_groups(embed(gram_counts(rows, key, "text", model), key, model), rows, key, model)
    elif strategy == "inrow":
        h = rows.select(key, in_row_h0(F.col("text"), model).alias("h0"))
    else:
        raise ValueError(f"no strategy is named {strategy}")
    z = h.select(key, hidden(F.col("h0"), model).alias("h1")).select(key, logits(F.col("h1"), model).alias("z"))
    return z.select(key, argmax_label(F.col("z"), model).alias("label"), F.array_max("z").alias("score"))
