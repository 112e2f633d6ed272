"""Language identification by sparse multinomial logistic regression.

Features are character 1- to 3-grams of the lower-cased text, hashed into a fixed
number of slots, as an L2-normalised TF-IDF vector; document frequencies are those
of all rows that may be learned from. Training is follow-the-regularised-leader with an elastic-net
penalty (per-coordinate rates, exact zeros), one document at a time over a bounded
sample; a temperature fitted on documents that training has not seen calibrates
the probabilities. Scoring is map-side.

Bounds: at most about ``per_class`` documents a language are learned from and the
model is ``slots x languages`` numbers, whatever the corpus.
Defined cases: a null text, an empty one and one without a letter is ``und`` with
score 0; without any labelled text every text is ``und``; with one language only,
every text with a letter is that language with score 1; equal probabilities go to
the first language by name; repeated rows are scored each; ids are not
read; further columns pass through or are ignored, and those named like the
new ones are replaced.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..plans.scratch import hash60
from .kernel import blocks, mix
from .rows import with_text_columns

SLOTS = 1 << 15
PER_CLASS = 500
ORDERS = (1, 2, 3)
UNDETERMINED = "und"


def gram_slots(code: np.ndarray, room: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The slot of every character n-gram and the place where it starts; ``room``: code points from each place to its text's end."""
    slots, places, run = [], [], np.zeros(len(code), np.uint64)
    for n in range(1, max(ORDERS) + 1):
        if len(code) < n:
            break
        run = run[: len(code) - n + 1] * np.uint64(0x100000001B3) + code[n - 1 :] + np.uint64(1)
        if n in ORDERS:
            at = np.flatnonzero(room[: len(run)] >= n)
            slots.append((mix(run[at] + np.uint64(n << 56)) & np.uint64(SLOTS - 1)).astype(np.int64))
            places.append(at)
    none = np.zeros(0, np.int64)
    return (np.concatenate(slots), np.concatenate(places)) if slots else (none, none)


def slot_counts(texts: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(text, slot, count) of the distinct slots of many texts, in order."""
    low = [t.lower() for t in texts]
    size = np.array([len(t) for t in low], np.int64)
    code = np.frombuffer("".join(low).encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64)
    owner = np.repeat(np.arange(len(texts)), size)
    slot, place = gram_slots(code, np.repeat(np.cumsum(size), size) - np.arange(len(code)))
    key = np.sort((owner[place] * SLOTS + slot).astype(np.uint32))  # 32 bits sort fastest
    first = np.flatnonzero(np.append(len(key) > 0, key[1:] != key[:-1])[: len(key)])
    found = key[first].astype(np.int64)
    return found // SLOTS, found % SLOTS, np.diff(np.append(first, len(key)))


def _groups(texts: list[str], most: int = 8) -> Iterator[list[str]]:
    for a in range(0, len(texts), most):
        yield texts[a : a + most]


def _slices(data: np.ndarray, offsets: np.ndarray) -> list[str]:
    raw = data.tobytes()
    return [raw[a:b].decode("utf-8", "replace") for a, b in zip(offsets, offsets[1:], strict=False)]


def _has_letter(text: str) -> bool:
    return any(map(str.isalpha, text))


def document_frequency(docs: DataFrame, text_col: str = "text") -> tuple[np.ndarray, int]:
    """In how many documents each slot occurs, over all rows; and the number of rows with text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(SLOTS + 1, np.int64)
        for _, data, offsets in blocks(batches, text_col):
            for texts in _groups(_slices(data, offsets)):
                total[:SLOTS] += np.bincount(slot_counts(texts)[1], minlength=SLOTS)
                total[SLOTS] += sum(map(bool, texts))
        some = np.flatnonzero(total)
        yield pa.record_batch({"at": pa.array(some.astype(np.int32)), "n": pa.array(total[some])})

    got = docs.select(text_col).mapInArrow(run, "at int, n long").groupBy("at").agg(F.sum("n").alias("n")).toArrow()
    out = np.zeros(SLOTS + 1, np.int64)
    out[got.column("at").to_numpy()] = got.column("n").to_numpy()
    return out[:SLOTS], int(out[SLOTS])


@dataclass
class LanguageModel:
    languages: list[str] = field(default_factory=list)
    idf: np.ndarray = field(default_factory=lambda: np.zeros(0, np.float32))
    weights: np.ndarray = field(default_factory=lambda: np.zeros((0, 0), np.float32))
    temperature: float = 1.0

    def vectors(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(text, slot, value) of the normalised TF-IDF vectors (sublinear term frequency)."""
        owner, at, count = slot_counts(texts)
        value = (1 + np.log(count)) * self.idf[at]
        norm = np.sqrt(np.bincount(owner, value * value, len(texts)))
        return owner, at, value / np.maximum(norm[owner], 1e-12)

    def logits(self, at: np.ndarray, value: np.ndarray) -> np.ndarray:
        return value @ self.weights[at]

    def predict(self, texts: list[str]) -> tuple[list[str], np.ndarray]:
        """Language and probability of every text."""
        label, score = [UNDETERMINED] * len(texts), np.zeros(len(texts))
        fit = np.array([i for i, t in enumerate(texts) if self.languages and t and _has_letter(t)], np.int64)
        if len(fit):
            owner, at, value = self.vectors([texts[i] for i in fit])
            cells = value[:, None] * self.weights[at]
            z = np.stack([np.bincount(owner, cells[:, k], len(fit)) for k in range(cells.shape[1])], 1) / self.temperature
            p = np.exp(z - z.max(1, keepdims=True))
            for i, k in zip(fit, p.argmax(1), strict=True):
                label[i] = self.languages[k]
            score[fit] = p.max(1) / p.sum(1)
        return label, score


def train_ftrl(model: LanguageModel, vectors: list, labels: np.ndarray, epochs: int = 3, alpha: float = 0.5, beta: float = 1.0, l1: float = 1e-3, l2: float = 1e-3, seed: int = 7) -> None:
    """Per-coordinate follow-the-regularised-leader (proximal form); sets ``model.weights``."""
    classes = len(model.languages)
    z, n = np.zeros((SLOTS, classes)), np.zeros((SLOTS, classes))
    target = np.eye(classes)
    order = np.random.default_rng(seed)

    def weights(at: np.ndarray) -> np.ndarray:
        za = z[at]
        return np.where(np.abs(za) <= l1, 0.0, -(za - np.sign(za) * l1) / ((beta + np.sqrt(n[at])) / alpha + l2))

    for _ in range(epochs):
        for i in order.permutation(len(vectors)):
            at, value = vectors[i]
            w = weights(at)
            s = value @ w
            p = np.exp(s - s.max())
            g = value[:, None] * (p / p.sum() - target[labels[i]])
            z[at] += g - (np.sqrt(n[at] + g * g) - np.sqrt(n[at])) / alpha * w
            n[at] += g * g
    model.weights = weights(np.arange(SLOTS)).astype(np.float32)


def calibrate(model: LanguageModel, vectors: list, labels: np.ndarray) -> None:
    """The temperature of least cross-entropy on a fixed grid."""
    if not len(vectors):
        return
    logits = np.stack([model.logits(*v) for v in vectors])
    best = (np.inf, 1.0)
    for t in np.geomspace(0.02, 10, 80):
        s = logits / t
        s = s - s.max(1, keepdims=True)
        loss = float((np.log(np.exp(s).sum(1)) - s[np.arange(len(s)), labels]).mean())
        best = min(best, (loss, float(t)))
    model.temperature = best[1]


def fit(docs: DataFrame, labelled: DataFrame, text_col: str = "text", lang_col: str = "lang", per_class: int = PER_CLASS) -> LanguageModel:
    """Learns from ``labelled`` (rows of text and language, a bounded sample of them); document frequencies from ``docs``, all rows that may be learned from."""
    usable = labelled.where(F.col(lang_col).isNotNull() & F.col(text_col).isNotNull() & (F.length(text_col) > 0))
    counts = {r[0]: r[1] for r in usable.groupBy(lang_col).agg(F.count(F.lit(1))).collect()}
    if not counts:
        return LanguageModel()
    df, rows = document_frequency(docs, text_col)
    model = LanguageModel(sorted(counts), np.log((1 + rows) / (1 + df)).astype(np.float32) + np.float32(1))
    if len(counts) == 1:
        model.weights = np.ones((SLOTS, 1), np.float32)
        return model
    share = F.create_map(*[x for k, n in counts.items() for x in (F.lit(k), F.lit(min(1.0, per_class / n) * float(1 << 60)))])
    place = F.create_map(*[x for i, k in enumerate(model.languages) for x in (F.lit(k), F.lit(i))])
    held = docs.sparkSession.sparkContext.broadcast(model)

    def vectors(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a in range(0, batch.num_rows, 64):
                part = batch.slice(a, 64)
                owner, at, value = held.value.vectors(part.column(1).to_pylist())
                cut = pa.array(np.searchsorted(owner, np.arange(part.num_rows + 1)).astype(np.int32))
                lists = [pa.ListArray.from_arrays(cut, pa.array(x)) for x in (at.astype(np.int32), value.astype(np.float32))]
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(2), *lists], names=["id", "label", "at", "value"])

    # Drawn by the hash of the text, each text once: the sample stays bounded however many rows share a text or an id.
    draw = usable.select(hash60(F.concat_ws(":", F.lit("lang"), F.col(text_col))).alias("id"), F.col(text_col).alias("text"), F.col(lang_col).alias("lang"))
    chosen = draw.where(F.col("id").cast("double") <= share[F.col("lang")]).dropDuplicates(["id", "lang"])
    sample = chosen.select("id", "text", place[F.col("lang")].cast("int").alias("label"))
    got = sample.mapInArrow(vectors, "id long, label int, at array<int>, value array<float>").toArrow().sort_by([("id", "ascending"), ("label", "ascending")])
    labels = got.column("label").to_numpy()
    made = [(np.asarray(a.values), np.asarray(v.values, np.float64)) for a, v in zip(got.column("at"), got.column("value"), strict=True)]
    hold = np.arange(len(labels)) % 5 == 0
    train_ftrl(model, [v for v, h in zip(made, hold, strict=True) if not h], labels[~hold])
    calibrate(model, [v for v, h in zip(made, hold, strict=True) if h], labels[hold])
    return model


def score(docs: DataFrame, model: LanguageModel, text_col: str = "text", keep: list[str] | None = None) -> DataFrame:
    """``keep`` (default: all) columns of ``docs`` with ``lang_pred`` and ``score``."""
    held = docs.sparkSession.sparkContext.broadcast(model)

    def make():
        def run(data, offsets):
            made = [held.value.predict(texts) for texts in _groups(_slices(data, offsets))]
            return {"lang_pred": pa.array([x for m in made for x in m[0]], pa.string()), "score": np.concatenate([m[1] for m in made])}

        return run

    return with_text_columns(docs, text_col, make, {"lang_pred": T.StringType(), "score": T.DoubleType()}, keep)
