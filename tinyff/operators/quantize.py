"""Low-bit embeddings: small signed codes and a scale for each row, part of a row or matrix."""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .features import Template
from .model import Network


def limit(bits: int) -> int:
    return 2 ** (bits - 1) - 1


def round_half_away(x):
    return np.sign(x) * np.floor(np.abs(x) + 0.5)


def scale_of(w: Column, bits: int) -> Column:
    return F.array_max(F.transform(w, lambda x: F.abs(x.cast("double")))) / limit(bits)


def encode(emb: DataFrame, column: str = "w", bits: int = 8, scale: str = "row", group: int = 16) -> DataFrame:
    """Adds ``scale`` and ``codes``; where all numbers are zero the scale is 0 and so are the codes.

    ``scale``: row; matrix for one scale in all; or group for an array of scales, one for every ``group`` numbers of a row.
    """
    if scale == "group":
        parts = F.transform(F.sequence(F.lit(1), F.size(column), F.lit(group)), lambda i: F.slice(F.col(column), i, F.lit(group)))
        scaled = emb.withColumn("scale", F.transform(parts, lambda p: scale_of(p, bits)))
        one = lambda i: F.element_at("scale", F.floor(i / group).cast("int") + 1)
        code = lambda x, i: F.when(one(i) == 0, 0).otherwise(F.round(x.cast("double") / one(i))).cast("int")
        return scaled.withColumn("codes", F.transform(column, code))
    s = scale_of(F.col(column), bits)
    if scale == "matrix":
        top = emb.agg(F.max(s).alias("scale"))
        scaled = emb.crossJoin(F.broadcast(top))  # a single row
    else:
        scaled = emb.withColumn("scale", s)
    code = lambda x: F.when(F.col("scale") == 0, 0).otherwise(F.round(x.cast("double") / F.col("scale"))).cast("int")
    return scaled.withColumn("codes", F.transform(column, code))


def decode(quantized: DataFrame, group: int = 16) -> DataFrame:
    """Adds ``restored``; an array of scales holds one for every ``group`` numbers."""
    if quantized.schema["scale"].dataType.typeName() == "array":
        return quantized.withColumn("restored", F.transform("codes", lambda q, i: q * F.element_at("scale", F.floor(i / group).cast("int") + 1)))
    return quantized.withColumn("restored", F.transform("codes", lambda q: q * F.col("scale")))


def error(quantized: DataFrame, column: str = "w", by: str | None = None) -> DataFrame:
    """Largest and mean absolute error, and the largest error in units of the scale (at most one half)."""
    per = F.zip_with(column, F.transform("codes", lambda q: q * F.col("scale")), lambda a, b: F.abs(a.cast("double") - b))
    rows = quantized.select(*([by] if by else []), F.array_max(per).alias("most"), F.aggregate(per, F.lit(0.0), lambda a, x: a + x).alias("total"), F.size(per).alias("n"), "scale")
    grouped = rows.groupBy(by) if by else rows.groupBy()
    return grouped.agg(F.round(F.max("most"), 6).alias("max_error"), F.round(F.sum("total") / F.sum("n"), 6).alias("mean_error"), F.round(F.max(F.when(F.col("scale") > 0, F.col("most") / F.col("scale"))), 6).alias("max_in_scales"))


def quantize_matrix(m: np.ndarray, bits: int = 8, scale_dtype=np.float16, granularity: str = "row", group: int = 4) -> tuple[np.ndarray, np.ndarray]:
    """Codes, and scales of shape (rows or 1, parts of a row), as a network stores them."""
    width = group if granularity == "group" else m.shape[1]
    top = np.stack([np.abs(m[:, a : a + width]).max(1) for a in range(0, m.shape[1], width)], 1)
    if granularity == "matrix":
        top = top.max(0, keepdims=True)
    s = (top / limit(bits)).astype(scale_dtype).astype(np.float32)
    each = np.repeat(s, width, 1)[:, : m.shape[1]]
    q = np.clip(round_half_away(m / np.where(each > 0, each, 1)), -limit(bits), limit(bits))
    return np.where(each > 0, q, 0).astype(np.int16 if bits > 8 else np.int8), s


def restore_matrix(q: np.ndarray, s: np.ndarray) -> np.ndarray:
    return q.astype(np.float32) * np.repeat(s, -(-q.shape[1] // s.shape[1]), 1)[:, : q.shape[1]]


@dataclass
class CodedNetwork:
    """A network that is kept as codes and scales: embeddings are decoded as they are read, and only those read."""

    template: Template
    classes: list[str]
    codes: list[np.ndarray]
    scales: list[np.ndarray]
    w: np.ndarray
    c: np.ndarray
    beta: np.ndarray
    b: np.ndarray
    bits: int
    scale_bytes: int = 2
    resources: dict = field(default_factory=dict)

    logits = Network.logits

    def rows(self, group: int, ids: np.ndarray) -> np.ndarray:
        s = self.scales[group]
        return restore_matrix(self.codes[group][ids], s[ids] if len(s) > 1 else s)

    def product(self, group: int, counts: np.ndarray) -> np.ndarray:
        """Sums of embeddings: counts are multiplied by the scales and then by the codes."""
        q, s = self.codes[group], self.scales[group]
        width = -(-q.shape[1] // s.shape[1])
        return np.concatenate([(counts * s[:, j]) @ q[:, j * width : (j + 1) * width].astype(np.float32) for j in range(s.shape[1])], 1)


def coded(net: Network, bits: int = 8, scale_dtype=np.float16, granularity: str = "row", group: int = 4) -> CodedNetwork:
    """The network in codes of ``bits``."""
    both = [quantize_matrix(e, bits, scale_dtype, granularity, group) for e in net.embeddings]
    return CodedNetwork(net.template, net.classes, [q for q, _ in both], [s for _, s in both], net.w, net.c, net.beta, net.b, bits, np.dtype(scale_dtype).itemsize, dict(net.resources))


def restored(net: CodedNetwork) -> Network:
    """The network of decoded embeddings, for comparison."""
    return Network(net.template, net.classes, [restore_matrix(q, np.broadcast_to(s, (len(q), s.shape[1]))) for q, s in zip(net.codes, net.scales, strict=True)], net.w, net.c, net.beta, net.b, dict(net.resources))
