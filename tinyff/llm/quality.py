"""Text quality by a generalised additive model with pairwise interactions.

Each text gives a short vector of counts and shares. Every feature is binned at
quantiles; boosting visits the features cyclically and adds a shallow tree's step
to the feature's lookup table; the strongest pairs of features then get small
two-way tables in the same way. A score is the sum of the tables' entries at the
text's bins, so scoring is a few vectorised additions.

Bounds: tables are fitted on at most about ``2 * per_class`` labelled texts.
Defined cases: null and empty texts have the all-zero vector and a score; without
labels of both classes every score is the share of good labels (0 without any);
null labels and ids teach nothing, an id labelled twice counts once with the larger
label, and of several texts under an id the first in byte order is learned from;
equal features share a bin and a score; repeated rows are scored each; further
columns pass through or are ignored, and those named score or predicted are replaced.
"""

from __future__ import annotations

from dataclasses import dataclass, field
from itertools import combinations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .kernel import BLANK_SPLIT, Alphabet, Words
from .rows import label_sample, one_text_each, with_text_columns

PER_CLASS = 8000
#: Scores from this value on predict 1.
THRESHOLD = 0.3
_LINES = Alphabet(lambda b: b != 0x0A, fold=False)
_CLASSES = {"small": range(0x61, 0x7B), "capital": range(0x41, 0x5B), "digit": range(0x30, 0x3A), "blank": b" \t\r\x0b\x0c", "newline": b"\n", "stop": b".,;:?'\"()-", "junk": b"#$%&*|!<>{}[]=+~^_@\\/`", "wide": range(0x80, 0x100)}
_CODE = np.zeros(256, np.int64)
for _i, _bytes in enumerate(_CLASSES.values(), 1):
    _CODE[list(_bytes)] = _i
FEATURES = ("bytes", "words", "word_bytes", *(f"{c}_share" for c in _CLASSES), "distinct_words", "distinct_lines", "short_words", "long_words", "line_words")


def features(data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """One row of ``FEATURES`` per text of a block."""
    n, size = len(offsets) - 1, np.diff(offsets)
    row = np.repeat(np.arange(n), size)
    kinds = np.bincount(row * 9 + _CODE[data], minlength=9 * n).reshape(n, 9)[:, 1:]
    words, lines = Words(data, offsets, BLANK_SPLIT), Words(data, offsets, _LINES)

    def distinct(found: Words) -> np.ndarray:
        owner = np.repeat(np.arange(n), np.diff(found.bounds))
        order = np.lexsort((found.hash, owner))
        h, o = found.hash[order], owner[order]
        first = np.ones(len(h), bool)
        first[1:] = (h[1:] != h[:-1]) | (o[1:] != o[:-1])
        return np.bincount(o[first], minlength=n)

    def share(mask: np.ndarray) -> np.ndarray:
        total = np.append(0, np.cumsum(mask))
        return (total[words.bounds[1:]] - total[words.bounds[:-1]]) / np.maximum(count, 1)

    count, line_count = np.diff(words.bounds), np.diff(lines.bounds)
    length = words.end - words.start
    some = np.maximum(size, 1)[:, None]
    return np.column_stack([np.log1p(size), np.log1p(count), share(length), kinds / some, distinct(words) / np.maximum(count, 1), distinct(lines) / np.maximum(line_count, 1), share(length <= 3), share(length > 16), count / np.maximum(line_count, 1)])


def _splits(grad: np.ndarray, hess: np.ndarray, leaves: int, l2: float) -> np.ndarray:
    """Newton steps of a tree with at most ``leaves`` leaves over ordered bins, grown by the best gain."""
    g, h = np.append(0, np.cumsum(grad)), np.append(0, np.cumsum(hess))
    worth = lambda a, b: (g[b] - g[a]) ** 2 / (h[b] - h[a] + l2)
    edges = [0, len(grad)]
    for _ in range(leaves - 1):
        best = (1e-9, None)
        for a, b in zip(edges, edges[1:], strict=False):
            if b - a > 1:
                c = np.arange(a + 1, b)
                gain = worth(a, c) + worth(c, b) - worth(a, b)
                k = int(gain.argmax())
                if gain[k] > best[0]:
                    best = (gain[k], int(c[k]))
        if best[1] is None:
            break
        edges = sorted([*edges, best[1]])
    out = np.zeros(len(grad))
    for a, b in zip(edges, edges[1:], strict=False):
        out[a:b] = -(g[b] - g[a]) / (h[b] - h[a] + l2)
    return out


@dataclass
class QualityModel:
    cuts: list[np.ndarray] = field(default_factory=list)
    base: float = 0.0
    single: np.ndarray = field(default_factory=lambda: np.zeros((0, 0)))
    coarse: np.ndarray = field(default_factory=lambda: np.zeros((0, 0), np.int64))
    pairs: list[tuple[int, int]] = field(default_factory=list)
    pair_tables: np.ndarray = field(default_factory=lambda: np.zeros((0, 0, 0)))
    prior: float = 0.0

    def bins(self, x: np.ndarray) -> np.ndarray:
        return np.column_stack([np.searchsorted(c, x[:, j], "right") for j, c in enumerate(self.cuts)])

    def logits(self, x: np.ndarray) -> np.ndarray:
        b = self.bins(x)
        out = np.full(len(x), self.base)
        for j in range(b.shape[1]):
            out += self.single[j, b[:, j]]
        for (i, j), table in zip(self.pairs, self.pair_tables, strict=True):
            out += table[self.coarse[i, b[:, i]], self.coarse[j, b[:, j]]]
        return out

    def scores(self, x: np.ndarray) -> np.ndarray:
        if not self.cuts:
            return np.full(len(x), self.prior)
        return 1 / (1 + np.exp(-np.clip(self.logits(x), -30, 30)))


def boost(x: np.ndarray, y: np.ndarray, weight: np.ndarray, bins: int = 32, rounds: int = 150, pair_rounds: int = 40, pairs: int = 8, grid: int = 8, rate: float = 0.1, l2: float = 5.0) -> QualityModel:
    """Cyclic boosting of per-feature tables, then of the tables of the ``pairs`` most promising pairs."""
    model = QualityModel([np.unique(np.quantile(x[:, j], np.linspace(0, 1, bins + 1)[1:-1])) for j in range(x.shape[1])])
    width = max(len(c) for c in model.cuts) + 1
    b = model.bins(x)
    rate0 = np.clip((weight * y).sum() / weight.sum(), 1e-4, 1 - 1e-4)
    model.base = float(np.log(rate0 / (1 - rate0)))
    model.single = np.zeros((x.shape[1], width))
    f = np.full(len(x), model.base)

    def slopes() -> tuple[np.ndarray, np.ndarray]:
        p = 1 / (1 + np.exp(-f))
        return weight * (p - y), weight * p * (1 - p)

    for _ in range(rounds):
        for j in range(x.shape[1]):
            g, h = slopes()
            step = rate * _splits(np.bincount(b[:, j], g, width), np.bincount(b[:, j], h, width), 4, l2)
            model.single[j] += step
            f += step[b[:, j]]
    model.coarse = np.stack([np.minimum(np.arange(width) * grid // max(len(c) + 1, 1), grid - 1) for c in model.cuts])
    small = np.column_stack([model.coarse[j, b[:, j]] for j in range(x.shape[1])])
    g, h = slopes()
    gain = {}
    for i, j in combinations(range(x.shape[1]), 2):
        cell = small[:, i] * grid + small[:, j]
        gain[i, j] = float((np.bincount(cell, g, grid * grid) ** 2 / (np.bincount(cell, h, grid * grid) + l2)).sum())
    model.pairs = sorted(gain, key=lambda k: (-gain[k], k))[:pairs]
    model.pair_tables = np.zeros((len(model.pairs), grid, grid))
    for _ in range(pair_rounds):
        for k, (i, j) in enumerate(model.pairs):
            g, h = slopes()
            cell = small[:, i] * grid + small[:, j]
            gg, hh = np.bincount(cell, g, grid * grid).reshape(grid, grid), np.bincount(cell, h, grid * grid).reshape(grid, grid)
            side = _splits(gg.sum(1), hh.sum(1), 2, l2)
            step = np.zeros((grid, grid))
            for value in np.unique(side):  # a split of the first feature, then one of the second in each half
                at = side == value
                step[at] = _splits(gg[at].sum(0), hh[at].sum(0), 2, l2)
            model.pair_tables[k] += rate * step
            f += rate * step.ravel()[cell]
    return model


def fit(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality", per_class: int = PER_CLASS) -> QualityModel:
    sample, counts = label_sample(labels, id_col, label_col, per_class)
    total = sum(counts.values())
    prior = counts.get(1, 0) / total if total else 0.0
    if not counts.get(1) or not counts.get(0):
        return QualityModel(prior=prior)
    # The ids are bounded by the sample.
    texts = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text")).join(F.broadcast(sample), "id")
    texts = one_text_each(texts)

    def make():
        return lambda data, offsets: {f"f{j}": c for j, c in enumerate(features(data, offsets).T)}

    got = with_text_columns(texts, "text", make, {f"f{j}": T.DoubleType() for j in range(len(FEATURES))}, ["id", "label"]).toArrow().to_pandas().sort_values("id")
    if got["label"].nunique() < 2:
        return QualityModel(prior=prior)
    x, y = got[[f"f{j}" for j in range(len(FEATURES))]].to_numpy(float), (got["label"] == 1).to_numpy(float)
    weight = np.where(y == 1, prior / y.mean(), (1 - prior) / (1 - y.mean()))
    return boost(x, y, weight)


def score(docs: DataFrame, model: QualityModel, text_col: str = "text", keep: list[str] | None = None) -> DataFrame:
    """``keep`` (default: all) columns of ``docs`` with ``score`` and ``predicted``."""
    held = docs.sparkSession.sparkContext.broadcast(model)

    def make():
        def run(data, offsets):
            s = held.value.scores(features(data, offsets))
            return {"score": s, "predicted": (s >= THRESHOLD).astype(np.int32)}

        return run

    return with_text_columns(docs, text_col, make, {"score": T.DoubleType(), "predicted": T.IntegerType()}, keep)
