"""Toxicity by two class-conditional Kneser-Ney word models.

Toxic and ordinary texts each get an interpolated bigram model: discounted bigram
counts, then discounted continuation counts of the class (distinct left
neighbours), then one backoff distribution that both classes share, counted over
the whole corpus. The discount grows with the square root of a count, so a rare
expression is left to the shared backoff and only well-attested differences speak.

The two log-likelihoods are compared word by word. Their length-normalised
difference over the whole text says little where a few words in a long text decide
(the README has figures), so the score is a logistic calibration of that difference,
of its part above some marks (also length-normalised), of the numbers and the shares
of words above the marks and of the number of words: what some marked words mean
depends on how many words stand around them. It is fitted on labelled texts that the
models have not seen.

Bounds: at most about ``per_class`` labelled texts a class are learned from, so
the broadcast model is bounded; shared counts cover all documents; every whole
text is scored, map-side.

Defined cases: null and empty texts are scored as texts of no words; without
labels of both classes every score is the share of toxic labels (0 without any);
null labels and ids teach nothing, an id labelled twice counts once with the larger
label, and of several texts under an id the first in byte order is learned from;
repeated rows are scored each; further columns pass through or are ignored, and
those named score or predicted are replaced.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..plans.scratch import materialise
from .kernel import ALNUM, Lookup, Words, blocks, mix
from .rows import fold_of, label_sample, logistic, one_text_each, with_text_columns

PER_CLASS = 3000
#: Percent of the labelled sample that the word models learn from; the rest calibrates.
MODEL_SHARE = 65
#: A count n is discounted by Z * sqrt(n), at most by n.
Z = 2.0
#: Words whose log-ratio exceeds these values are also counted by themselves for the calibration.
MARKS = (0.5, 1.0, 1.5, 2.0, 3.0, 4.0)
MEASURES = ("mean", "words", *(f"{m}{k}" for m in ("excess", "over") for k in range(len(MARKS))))


def _discount(n):
    return np.minimum(n, Z * np.sqrt(n))


def _pair(h: np.ndarray, w: np.ndarray) -> np.ndarray:
    return mix(h * np.uint64(0x9E3779B97F4A7C15) + w)


def _left(words: Words) -> np.ndarray:
    """Each word's left neighbour, 0 at the start of a text."""
    left = np.append(np.uint64(0), words.hash[:-1])[: len(words.hash)]
    left[words.bounds[:-1][words.bounds[:-1] < len(left)]] = 0
    return left


@dataclass
class ToxicityModel:
    words: np.ndarray = field(default_factory=lambda: np.zeros(0, np.uint64))
    word_ratio: np.ndarray = field(default_factory=lambda: np.zeros(0))
    unknown_ratio: float = 0.0
    context_ratio: np.ndarray = field(default_factory=lambda: np.zeros(0))
    pairs: np.ndarray = field(default_factory=lambda: np.zeros(0, np.uint64))
    pair_ratio: np.ndarray = field(default_factory=lambda: np.zeros(0))
    beta: np.ndarray | None = None
    center: np.ndarray = field(default_factory=lambda: np.zeros(1))
    scale: np.ndarray = field(default_factory=lambda: np.ones(1))
    prior: float = 0.0

    def features(self, got: dict) -> np.ndarray:
        """Length-normalised: the mean log-ratio, the mean excess over each mark and the share of words above it; how many words exceed it, and how many there are."""
        over = [got[f"over{k}"] for k in range(len(MARKS))]
        shares = [x / np.maximum(got["words"], 1) for x in over]
        return np.column_stack([got["mean"], *(got[f"excess{k}"] for k in range(len(MARKS))), *map(np.log1p, over), *shares, np.log1p(got["words"])])

    def scores(self, got: dict) -> np.ndarray:
        if self.beta is None:
            return np.full(len(got["mean"]), self.prior)
        x = (self.features(got) - self.center) / self.scale
        return 1 / (1 + np.exp(-np.clip(x @ self.beta[:-1] + self.beta[-1], -30, 30)))


def _ratios(model: ToxicityModel):
    """A block function: per text the mean over its words of log p(word | toxic) - log p(word | ordinary), and its words."""

    def make():
        table, pairs = Lookup(model.words), Lookup(model.pairs)
        word_ratio = np.append(model.word_ratio, model.unknown_ratio)
        context = np.append(model.context_ratio, 0.0)
        at, known = table.find(np.zeros(1, np.uint64))
        start = at[0] if known[0] else len(model.words)

        def run(data: np.ndarray, offsets: np.ndarray) -> dict:
            words = Words(data, offsets, ALNUM)
            at, known = table.find(words.hash)
            at = np.where(known, at, len(model.words))
            ratio = word_ratio[at]
            left = _left(words)
            before = np.append(len(model.words), at[:-1])[: len(at)]
            before[left == 0] = start
            ratio += context[before]
            both = np.flatnonzero(known & (before < len(model.words)))
            hit, seen = pairs.find(_pair(left[both], words.hash[both]))
            ratio[both[seen]] = model.pair_ratio[hit[seen]]
            n = np.diff(words.bounds)

            def total(x: np.ndarray) -> np.ndarray:
                run = np.append(0.0, np.cumsum(x))
                return run[words.bounds[1:]] - run[words.bounds[:-1]]

            out = {"mean": total(ratio) / np.maximum(n, 1), "words": n.astype(float)}
            for k, mark in enumerate(MARKS):
                out[f"excess{k}"] = total(np.maximum(ratio - mark, 0)) / np.maximum(n, 1)
                out[f"over{k}"] = np.rint(total(ratio > mark))
            return out

        return run

    return make


def _bigrams(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(text, label) -> one row per text and word: left neighbour (0 at the start), word, label."""
    for rows, data, offsets in blocks(batches):
        words = Words(data, offsets, ALNUM)
        left = _left(words)
        label = np.repeat(rows.column(rows.schema.get_field_index("label")).to_numpy(zero_copy_only=False), np.diff(words.bounds))
        yield pa.record_batch({"h": pa.array(left.view(np.int64)), "w": pa.array(words.hash.view(np.int64)), "toxic": pa.array((label == 1).astype(np.int8))})


def _numpy(df: DataFrame) -> dict[str, np.ndarray]:
    t = df.toArrow()
    return {c: t.column(c).to_numpy() for c in t.column_names}


def shared_counts(docs: DataFrame, text: str, vocabulary: np.ndarray) -> tuple[np.ndarray, int]:
    """Occurrences of each vocabulary word in all documents, and of all words."""
    held = docs.sparkSession.sparkContext.broadcast(vocabulary)

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = Lookup(held.value)
        seen = np.zeros(len(held.value) + 1, np.int64)
        for _, data, offsets in blocks(batches, text):
            at, known = table.find(Words(data, offsets, ALNUM).hash)
            seen += np.bincount(np.where(known, at, len(held.value)), minlength=len(seen))
        some = np.flatnonzero(seen)
        yield pa.record_batch({"at": pa.array(some.astype(np.int32)), "n": pa.array(seen[some])})

    got = _numpy(docs.select(text).mapInArrow(count, "at int, n long").groupBy("at").agg(F.sum("n").alias("n")))
    counts = np.zeros(len(vocabulary) + 1, np.int64)
    counts[got["at"]] = got["n"]
    return counts[:-1], int(counts.sum())


def fit(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic", per_class: int = PER_CLASS) -> ToxicityModel:
    """Learns from the rows of ``labels`` (a bounded sample) and the texts they name; shared counts from all ``docs``."""
    spark = docs.sparkSession
    sample, counts = label_sample(labels, id_col, label_col, per_class)
    total = sum(counts.values())
    prior = counts.get(1, 0) / total if total else 0.0
    if not counts.get(1) or not counts.get(0):
        return ToxicityModel(prior=prior)
    # At most about 2 * per_class ids: bounded by the sample.
    texts = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text")).join(F.broadcast(sample), "id").select("id", "text", "label", "draw")
    texts = materialise(one_text_each(texts), "toxic-sample")
    tokens = texts.where(F.col("draw") < MODEL_SHARE).select("text", F.col("label").cast("int")).mapInArrow(_bigrams, "h long, w long, toxic tinyint")
    pairs = materialise(tokens.groupBy("h", "w").agg(F.sum(F.col("toxic").cast("long")).alias("t"), F.sum(1 - F.col("toxic").cast("long")).alias("o")), "toxic-pairs")
    cut = lambda c: F.least(F.col(c).cast("double"), F.lit(Z) * F.sqrt(c))
    least = int(Z * Z)
    uni = pairs.groupBy("w").agg(F.count_if(F.col("t") > 0).alias("t"), F.count_if(F.col("o") > 0).alias("o"))
    sums = uni.agg(F.sum("t").alias("kt"), F.sum("o").alias("ko"), F.sum(cut("t")).alias("dt"), F.sum(cut("o")).alias("do")).collect()[0]
    if sums["kt"] is None:  # none of the labelled texts is there
        return ToxicityModel(prior=prior)
    known = _numpy(uni.where((F.col("t") > least) | (F.col("o") > least)))
    big = _numpy(pairs.where((F.col("t") > least) | (F.col("o") > least)))
    h, w, word = (x.view(np.uint64) for x in (big["h"], big["w"], known["w"]))
    # Both words of every pair above the discount are held, however few neighbours they have (0: the start of a text).
    vocabulary = np.unique(np.concatenate([word, h, w]))
    at = np.searchsorted(vocabulary, word)
    kt, ko = (np.zeros(len(vocabulary)) for _ in range(2))
    # A continuation count up to the discount leaves nothing, so that the words known by pairs alone count as 0.
    kt[at], ko[at] = known["t"], known["o"]
    seen, all_words = shared_counts(docs, text_col, vocabulary)
    shared = (seen + 0.5) / (all_words + 0.5 * (len(vocabulary) + 1))
    back_t, back_o = (sums["dt"] + 1) / (sums["kt"] + 1), (sums["do"] + 1) / (sums["ko"] + 1)
    p_t = (kt - _discount(kt)) / (sums["kt"] + 1) + back_t * shared
    p_o = (ko - _discount(ko)) / (sums["ko"] + 1) + back_o * shared
    ctx = _numpy(pairs.groupBy("h").agg(F.sum("t").alias("t"), F.sum("o").alias("o"), F.sum(cut("t")).alias("dt"), F.sum(cut("o")).alias("do")).where((F.col("t") > least) | (F.col("o") > least)))
    lam_t, lam_o, n_t, n_o = (np.ones(len(vocabulary)) for _ in range(4))
    table = Lookup(vocabulary)
    at, have = table.find(ctx["h"].view(np.uint64))
    at = at[have]
    n_t[at], n_o[at] = (np.maximum(ctx[c][have], 1) for c in ("t", "o"))
    lam_t[at] = np.where(ctx["t"][have] > 0, ctx["dt"][have] / n_t[at], 1.0)
    lam_o[at] = np.where(ctx["o"][have] > 0, ctx["do"][have] / n_o[at], 1.0)
    lam_t, lam_o = np.maximum(lam_t, 1e-3), np.maximum(lam_o, 1e-3)
    ih, iw, bt, bo = np.searchsorted(vocabulary, h), np.searchsorted(vocabulary, w), big["t"].astype(float), big["o"].astype(float)
    q_t = (bt - _discount(bt)) / n_t[ih] + lam_t[ih] * p_t[iw]
    q_o = (bo - _discount(bo)) / n_o[ih] + lam_o[ih] * p_o[iw]
    key = _pair(h, w)
    order = np.argsort(key)
    model = ToxicityModel(vocabulary, np.log(p_t / p_o), float(np.log(back_t / back_o)), np.log(lam_t / lam_o), key[order], np.log(q_t / q_o)[order], prior=prior)
    held = spark.sparkContext.broadcast(model)
    rest = with_text_columns(texts.where(F.col("draw") >= MODEL_SHARE), "text", lambda: _ratios(held.value)(), dict.fromkeys(MEASURES, T.DoubleType()), ["label"])
    got = _numpy(rest)
    y = (got["label"] == 1).astype(float)
    if 0 < y.sum() < len(y):
        x = model.features(got)
        model.center, model.scale = x.mean(0), x.std(0) + 1e-9
        rate = np.where(y == 1, prior / max(y.mean(), 1e-9), (1 - prior) / max(1 - y.mean(), 1e-9))
        model.beta = logistic((x - model.center) / model.scale, y, rate, l2=1e-4)
    return model


def score(docs: DataFrame, model: ToxicityModel, text_col: str = "text", keep: list[str] | None = None) -> DataFrame:
    """``keep`` (default: all) columns of ``docs`` with ``score`` and ``predicted``."""
    held = docs.sparkSession.sparkContext.broadcast(model)

    def make():
        ratios = _ratios(held.value)()

        def run(data, offsets):
            got = ratios(data, offsets)
            s = held.value.scores(got)
            return {"score": s, "predicted": (s >= 0.5).astype(np.int32)}

        return run

    return with_text_columns(docs, text_col, make, {"score": T.DoubleType(), "predicted": T.IntegerType()}, keep)


def train_labels(labels: DataFrame, label_col: str = "toxic", id_col: str = "doc_id") -> DataFrame:
    """Labelled rows that are not held out."""
    return labels.select(id_col, label_col).where(fold_of(F.col(id_col)) != 0)
