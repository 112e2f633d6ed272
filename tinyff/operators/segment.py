"""Word segmentation by a transition system over characters.

State: a stack of word starts and a buffer of characters. SPLIT starts a word with
the next character; MERGE adds it to the current word. MERGE is illegal on an empty
stack, so a text has as many actions as characters and the first is SPLIT.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import gram_buckets
from ..functions.text import chars
from . import train
from .features import FeatureGroup, Template
from .forward import text_blocks
from .model import Network
from .train import Bags

SPLIT, MERGE = "SPLIT", "MERGE"


class TransitionSystem:
    def __init__(self, characters: list[str]):
        self.characters, self.next, self.stack, self.trace = characters, 0, [], []

    def legal(self) -> list[str]:
        if self.next == len(self.characters):
            return []
        return [SPLIT, MERGE] if self.stack else [SPLIT]

    def apply(self, action: str) -> None:
        if action not in self.legal():
            raise ValueError(f"{action} is not legal here")
        if action == SPLIT:
            self.stack.append(self.next)
        self.next += 1
        self.trace.append(action)

    @property
    def words(self) -> list[str]:
        ends = [*self.stack[1:], self.next]
        return ["".join(self.characters[a:b]) for a, b in zip(self.stack, ends, strict=True)]


def words_of(sentence: Column) -> Column:
    return F.filter(F.split(sentence, r"[ \t\n\r]+"), lambda w: w != "")


def gold_actions(words: Column) -> Column:
    """Actions of a list of words: one letter per character, S at word starts, else M."""
    return F.array_join(F.transform(words, lambda w: F.concat(F.lit("S"), F.repeat(F.lit("M"), F.length(w) - 1))), "")


def apply(joined: Column, actions: Column) -> Column:
    """Words, joined by blanks, from characters and actions of one row."""
    pairs = F.arrays_zip(chars(joined).alias("c"), chars(actions).alias("a"))
    return F.ltrim(F.array_join(F.transform(pairs, lambda p: F.when(p["a"] == "S", F.concat(F.lit(" "), p["c"])).otherwise(p["c"])), ""))


def vocabulary(texts: list[str], n: int, least: int = 2) -> dict[str, int]:
    """Ids from 2 for n-grams that occur at least ``least`` times; 0 is padding, 1 unknown (which singletons train)."""
    seen = Counter(t[i : i + n] for t in texts for i in range(len(t) - n + 1))
    return {g: i for i, g in enumerate(sorted(g for g, c in seen.items() if c >= least), 2)}


UNI, BI = (-3, -2, -1, 0, 1, 2), (-2, -1, 0, 1)
HASHED = 64


def template(dim: int, uni: int, bi: int = 0, bi_dim: int = 16) -> Template:
    groups = [FeatureGroup("unigrams", uni, dim, slots=len(UNI)), FeatureGroup("previous", 3, 4, slots=2, kind="action")]
    if bi:
        groups.append(FeatureGroup("bigrams", bi, bi_dim, slots=len(BI), n=2))
    return Template(tuple(groups))


class Encoder:
    """Character windows to ids, by vocabularies or (``hashed``) by hashing."""

    def __init__(self, texts: list[str], bigrams: bool, hashed: bool = False):
        self.uni = None if hashed else vocabulary(texts, 1)
        self.bi = vocabulary(texts, 2) if bigrams else None
        self.sizes = (HASHED if hashed else len(self.uni) + 2, len(self.bi) + 2 if bigrams else 0)
        self.cache: dict[str, int] = {}

    @property
    def bytes(self) -> int:
        """Bytes of the vocabularies: every n-gram in UTF-8 and its end mark."""
        return sum(len(g.encode("utf-8", "surrogatepass")) + 1 for table in (self.uni, self.bi) if table for g in table)

    def one(self, c: str) -> int:
        if c == "\x00":
            return 0
        if self.uni is not None:
            return self.uni.get(c, 1)
        if c not in self.cache:
            self.cache[c] = int(gram_buckets(c, 1, HASHED)[0])
        return self.cache[c]

    def grid(self, text: str) -> tuple[np.ndarray, np.ndarray | None]:
        """Ids of all windows of a text: (length, unigram slots) and (length, bigram slots)."""
        pad = max(-UNI[0], UNI[-1] + 1)
        full = "\x00" * pad + text + "\x00" * pad
        ids = np.fromiter(map(self.one, full), np.int64, len(full))
        at = np.arange(len(text)) + pad
        uni = np.stack([ids[at + o] for o in UNI], 1)
        if self.bi is None:
            return uni, None
        known = self.bi.get
        two = np.fromiter((known(x + y, 1) for x, y in zip(full, full[1:], strict=False)), np.int64, len(full) - 1)
        return uni, np.stack([two[at + o] for o in BI], 1)


def _bags(uni: np.ndarray, bi: np.ndarray | None, previous: np.ndarray) -> Bags:
    cols = [*uni.T, *previous.T, *(bi.T if bi is not None else [])]
    groups = [0] * uni.shape[1] + [1, 1] + [2] * (bi.shape[1] if bi is not None else 0)
    every = np.arange(len(uni) + 1)
    return Bags(groups, [np.ascontiguousarray(c) for c in cols], [every] * len(cols))


def gold_data(sents: list[list[str]], enc: Encoder) -> tuple[Bags, np.ndarray]:
    uni, bi, prev, y = [], [], [], []
    for words in sents:
        text = "".join(words)
        if not text:
            continue
        a = np.concatenate([[0] + [1] * (len(w) - 1) for w in words])
        u, b = enc.grid(text)
        past = np.concatenate([[2, 2], a])[: len(a) + 1]
        uni.append(u)
        bi.append(b)
        prev.append(np.stack([past[1 : len(a) + 1], past[: len(a)]], 1))
        y.append(a)
    return _bags(np.concatenate(uni), np.concatenate(bi) if enc.bi is not None else None, np.concatenate(prev)), np.concatenate(y)


def start(sents: list[list[str]], dim: int = 64, bigrams: bool = False, hashed: bool = False, hidden: int = 64, seed: int = 0) -> tuple[Network, Encoder]:
    """An untrained network over the vocabularies of the sentences, which count as its resources."""
    enc = Encoder(["".join(s) for s in sents], bigrams, hashed)
    net = Network.random(template(dim, *enc.sizes), hidden, [SPLIT, MERGE], seed=dim + seed)
    net.resources["bytes"] = enc.bytes
    return net, enc


def word_f1_of(dev: list[list[str]], enc: Encoder):
    """The task's measure: word F1 of decoded held-out sentences."""
    texts, gold = ["".join(s) for s in dev], [spans([k for w in s for k in [0] + [1] * (len(w) - 1)]) for s in dev]
    return lambda net, _: _f1(gold, [spans(x) for x in decode(texts, net, enc)])


def build(sents: list[list[str]], dev: list[list[str]], dim: int = 64, bigrams: bool = False, hashed: bool = False, hidden: int = 64, epochs: int = 2, seed: int = 0) -> tuple[Network, Encoder]:
    """Learns from sentences as word lists; training stops early by the word F1 of decoded held-out sentences."""
    net, enc = start(sents, dim, bigrams, hashed, hidden, seed)
    net, _ = train.sgd(net, *gold_data(sents, enc), train.Settings(lr=0.1, epochs=epochs, seed=1 + seed), gold_data(dev, enc), every=500, metric=word_f1_of(dev, enc))
    return net, enc


def _f1(gold: list[set], pred: list[set]) -> float:
    return 2 * sum(len(g & p) for g, p in zip(gold, pred, strict=True)) / max(1, sum(map(len, gold)) + sum(map(len, pred)))


#: Characters whose windows are scored together.
BLOCK_CHARS = 1 << 17


class Scorer:
    """Action scores of every character for every pair of previous actions, all characters of a block at once.

    The hidden layer is linear in its inputs, so each window place has a table of its vocabulary's
    share in the hidden layer; a character adds up the rows of its window, and each of the four pairs
    of previous actions adds its own share.
    """

    def __init__(self, net: Network, enc: Encoder):
        self.net, self.enc, t = net, enc, net.template
        at, self.tables, self.past = 0, [], []
        for g, group in enumerate(t.groups):
            rows = net.rows(g, np.arange(group.vocab))
            for _ in range(group.slots):
                share = np.ascontiguousarray(rows @ net.w[:, at : at + group.dim].T)
                (self.past if group.kind == "action" else self.tables).append(share)
                at += group.dim

    def _out(self, hidden: np.ndarray, before: int, earlier: int) -> np.ndarray:
        return np.maximum(hidden + (self.past[0][before] + self.past[1][earlier]), 0) @ self.net.beta.T + self.net.b

    def log_odds(self, texts: list[str]) -> np.ndarray:
        """(characters of all texts, 4): log p(MERGE) - log p(SPLIT) after the pairs (before, earlier) = 00, 01, 10, 11.

        The second character of a text has only one action before it, which is SPLIT: its first column is that case.
        """
        grids = [self.enc.grid(t) for t in texts if t]
        cols = np.concatenate([g[0] for g in grids]).T
        if self.enc.bi is not None:
            cols = np.concatenate([cols, np.concatenate([g[1] for g in grids]).T])
        hidden = np.broadcast_to(self.net.c, (cols.shape[1], len(self.net.c))).copy()
        for table, ids in zip(self.tables, cols, strict=True):
            hidden += table[ids]
        out = np.empty((cols.shape[1], 4), np.float32)
        for k, (before, earlier) in enumerate(((0, 0), (0, 1), (1, 0), (1, 1))):
            z = self._out(hidden, before, earlier)
            out[:, k] = z[:, 1] - z[:, 0]
        size = np.array([len(t) for t in texts if t])
        second = (np.cumsum(size) - size + 1)[size > 1]
        z = self._out(hidden[second], 0, 2)
        out[second, 0] = z[:, 1] - z[:, 0]
        return out


def _greedy(merge: list[tuple[bool, bool, bool, bool]]) -> list[int]:
    """Follows the best action from character to character; ``merge``: by the pair of previous actions."""
    out, state = [0], 0
    for row in merge[1:]:
        a = row[state]
        out.append(int(a))
        state = (a << 1) | (state >> 1)
    return out


def _beam(odds: np.ndarray, beam: int) -> list[int]:
    """The best of ``beam`` hypotheses a character, by the sum of log-probabilities."""
    split, merge = -np.logaddexp(0, odds), -np.logaddexp(0, -odds)
    hyps = [(0.0, 0, [0])]
    for at in range(1, len(odds)):
        grown = [(p + float(x[at, s]), (a << 1) | (s >> 1), [*h, a]) for p, s, h in hyps for a, x in ((0, split), (1, merge))]
        hyps = sorted(grown, key=lambda h: -h[0])[:beam]
    return hyps[0][2]


def decode(texts: list[str], net: Network, enc: Encoder, beam: int = 1) -> list[list[int]]:
    """Greedy or beam decoding; 0 is SPLIT, which the first action always is."""
    scorer, out = Scorer(net, enc), [[] for _ in texts]
    full = [i for i, t in enumerate(texts) if t]
    for a, b in text_blocks([texts[i] for i in full], BLOCK_CHARS):
        mine = full[a:b]
        odds = scorer.log_odds([texts[i] for i in mine])
        ends = np.cumsum([len(texts[i]) for i in mine])
        better = (odds > 0).tolist()
        for i, end in zip(mine, ends.tolist(), strict=True):
            begin = end - len(texts[i])
            out[i] = _greedy(better[begin:end]) if beam == 1 else _beam(odds[begin:end], beam)
    return out


class Greedy:
    """Greedy decoding of many texts as one array of code points.

    A character's best actions depend on the ids of its window and on the two actions before it. Those of a window
    are scored once and remembered in a table of ``ROOM`` places, by the whole window; one that lost its place is
    scored again. The texts then take their actions in lock step.
    """

    ROOM_BITS, ID_BITS = 20, 10

    def __init__(self, net: Network, enc: Encoder):
        self.scorer, self.enc = Scorer(net, enc), enc
        self.ids = np.full(1 << 16, -1, np.int64)  # of code points, -1: not asked for yet
        self.keys, self.values = np.full(1 << self.ROOM_BITS, -1, np.int64), np.zeros(1 << self.ROOM_BITS, np.uint8)
        known = len(enc.uni) + 2 if enc.uni is not None else 0
        self.dense = 0 < known <= 1 << self.ID_BITS
        if self.dense and enc.bi is not None:
            self.bi = np.full((known, known), 1, np.int64)
            for g, i in enc.bi.items():
                self.bi[enc.one(g[0]), enc.one(g[1])] = i

    def _unigrams(self, code: np.ndarray) -> np.ndarray:
        out = self.ids[np.minimum(code, (1 << 16) - 1)]
        ask = np.flatnonzero((out < 0) | (code >= (1 << 16) - 1))
        for c in np.unique(code[ask]).tolist():
            i = self.enc.one(chr(c))
            out[ask[code[ask] == c]] = i
            if c < (1 << 16) - 1:
                self.ids[c] = i
        return out

    def _score(self, window: np.ndarray) -> np.ndarray:
        """Bits 0 to 3: MERGE is better after the pairs of actions 00, 01, 10, 11; bit 4: after one SPLIT at a text's begin. ``window``: (places, characters)."""
        scorer, out = self.scorer, np.empty(window.shape[1], np.uint8)
        for a in range(0, len(out), 1 << 14):
            w = window[:, a : a + (1 << 14)]
            cols = [*w] if self.enc.bi is None else [*w, *(self.bi[w[o - UNI[0]], w[o - UNI[0] + 1]] for o in BI)]
            hidden = np.broadcast_to(scorer.net.c, (w.shape[1], len(scorer.net.c))).copy()
            for table, ids in zip(scorer.tables, cols, strict=True):
                hidden += table[ids]
            bits = np.zeros(w.shape[1], np.uint8)
            for k, pair in enumerate(((0, 0), (0, 1), (1, 0), (1, 1), (0, 2))):
                z = scorer._out(hidden, *pair)
                bits |= (z[:, 1] - z[:, 0] > 0).astype(np.uint8) << k
            out[a : a + w.shape[1]] = bits
        return out

    def bits(self, code: np.ndarray, size: np.ndarray) -> np.ndarray:
        """The bits of every character of texts of ``size`` characters side by side."""
        before, behind = -UNI[0], UNI[-1]
        room = before + behind
        at = np.arange(len(code)) + np.repeat(np.arange(len(size)) * room + before, size)
        padded = np.zeros(len(code) + len(size) * room, np.int64)
        padded[at] = self._unigrams(code)
        key = np.zeros(len(code), np.int64)
        for o in UNI:
            key = (key << self.ID_BITS) | padded[at + o]
        place = ((key.view(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - self.ROOM_BITS)).astype(np.int64)
        out = self.values[place]
        miss = np.flatnonzero(self.keys[place] != key)
        if len(miss):
            fresh, first, back = np.unique(key[miss], return_index=True, return_inverse=True)
            made = self._score(np.stack([padded[at[miss[first]] + o] for o in UNI]))
            out[miss] = made[back]
            mine = place[miss[first]]
            # Of windows that want one place the last stays, with its own bits.
            last = np.unique(mine[::-1], return_index=True)[1]
            last = len(mine) - 1 - last
            self.keys[mine[last]], self.values[mine[last]] = fresh[last], made[last]
        return out

    def __call__(self, code: np.ndarray, size: np.ndarray) -> np.ndarray:
        """The actions of every character; 0 is SPLIT."""
        if not self.dense:
            text, ends = code.astype(np.uint32).tobytes().decode("utf-32-le", "surrogatepass"), np.cumsum(size)
            made = decode([text[e - n : e] for e, n in zip(ends.tolist(), size.tolist(), strict=True)], self.scorer.net, self.enc)
            return np.array([k for x in made for k in x], np.uint8)
        bits, out = self.bits(code, size), np.zeros(len(code), np.uint8)
        begin = (np.cumsum(size) - size)[np.argsort(-size, kind="stable")]
        longer = len(size) - np.searchsorted(np.sort(size), np.arange(int(size.max(initial=0))), "right")  # texts of more than t characters
        state = np.zeros(len(size), np.uint8)
        for t in range(1, len(longer)):
            n = longer[t]
            at, state = begin[:n] + t, state[:n]
            a = (bits[at] >> (state if t > 1 else np.uint8(4))) & 1
            out[at] = a
            state = (a << 1) | (state >> 1)
        return out


def _spans(split: np.ndarray) -> np.ndarray:
    """The end of the span that begins at a place; 0 where none begins."""
    begin = np.flatnonzero(split)
    out = np.zeros(len(split), np.int64)
    out[begin] = np.append(begin[1:], len(split))[: len(begin)]
    return out


def spans(actions: list[int]) -> set[tuple[int, int]]:
    starts = [i for i, a in enumerate(actions) if a == 0]
    return set(zip(starts, [*starts[1:], len(actions)], strict=True)) if actions else set()


COUNTS = "lang string, chars long, right long, both long, predicted long, gold long"


def evaluate(sents: DataFrame, decoder) -> DataFrame:
    """Character decisions and word spans against gold, summed by language; ``decoder``: list of texts -> list of actions.

    A decoder with a method ``kernel`` gives a function of code points and sizes of texts instead.
    """
    held = sents.sparkSession.sparkContext.broadcast(decoder)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kernel = held.value.kernel() if hasattr(held.value, "kernel") else None
        for batch in batches:
            words, many = batch.column("words").flatten(), np.diff(batch.column("words").offsets.to_numpy())
            length = pa.compute.utf8_length(words).to_numpy().astype(np.int64)
            size = np.bincount(np.repeat(np.arange(len(many)), many), length, len(many)).astype(np.int64)
            text = "".join(words.to_pylist())
            gold = np.ones(len(text), np.uint8)
            gold[(np.cumsum(length) - length)[length > 0]] = 0
            if kernel is not None:
                code = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.int64)
                pred = kernel(code, size)
            else:
                texts = [text[e - n : e] for e, n in zip(np.cumsum(size).tolist(), size.tolist(), strict=True)]
                pred = np.fromiter((k for x in held.value(texts) for k in x), np.uint8, len(text))
            ours, theirs = _spans(pred == 0), _spans(gold == 0)
            named = batch.column("lang").dictionary_encode(null_encoding="encode")
            lang = np.repeat(named.indices.to_numpy(), size)
            sums = [np.bincount(lang[hit], minlength=len(named.dictionary)) for hit in (np.ones(len(text), bool), pred == gold, (ours > 0) & (ours == theirs), ours > 0, theirs > 0)]
            yield pa.RecordBatch.from_arrays([named.dictionary, *(pa.array(x.astype(np.int64)) for x in sums)], names=["lang", "chars", "right", "both", "predicted", "gold"])

    return sents.select("lang", "words").mapInArrow(run, COUNTS).groupBy("lang").agg(*[F.sum(c).alias(c) for c in ("chars", "right", "both", "predicted", "gold")])


def rates(counts: DataFrame) -> DataFrame:
    p, r = F.col("both") / F.greatest("predicted", F.lit(1)), F.col("both") / F.greatest("gold", F.lit(1))
    return counts.select("lang", (F.col("right") / F.col("chars")).alias("char_accuracy"), p.alias("precision"), r.alias("recall"), (2 * F.col("both") / F.greatest(F.col("predicted") + F.col("gold"), F.lit(1))).alias("word_f1"))


# Baselines.


def one_word(texts: list[str]) -> list[list[int]]:
    return [[0] + [1] * (len(t) - 1) if t else [] for t in texts]


def every_char(texts: list[str]) -> list[list[int]]:
    return [[0] * len(t) for t in texts]


class MaxMatch:
    """Longest dictionary word from the left; a character that starts none is a word."""

    def __init__(self, sents: list[list[str]]):
        self.words = {w for s in sents for w in s}
        self.longest = max(map(len, self.words), default=1)

    def __call__(self, texts: list[str]) -> list[list[int]]:
        out = []
        for t in texts:
            a, at = [], 0
            while at < len(t):
                n = next((n for n in range(min(self.longest, len(t) - at), 1, -1) if t[at : at + n] in self.words), 1)
                a += [0] + [1] * (n - 1)
                at += n
            out.append(a)
        return out


class LinearSegmenter:
    """Averaged perceptron over the same windows; ``conjunctions`` adds hand-made pairs of them."""

    def __init__(self, conjunctions: bool = False):
        self.conjunctions, self.weights = conjunctions, {}

    def features(self, text: str, at: int, past: tuple[int, int]) -> list[str]:
        c = lambda o: text[at + o] if 0 <= at + o < len(text) else "\x00"
        f = [f"{o}:{c(o)}" for o in UNI] + [f"p:{past}"]
        if self.conjunctions:
            f += [f"{o}:{c(o)}{c(o + 1)}" for o in BI] + [f"t:{c(-1)}{c(0)}{c(1)}", f"q:{past[0]}{c(0)}"]
        return f

    def fit(self, sents: list[list[str]], epochs: int = 2) -> LinearSegmenter:
        w, total, step = {}, {}, 1
        for _ in range(epochs):
            for words in sents:
                text = "".join(words)
                gold, past = [k for x in words for k in [0] + [1] * (len(x) - 1)], (2, 2)
                for at, y in enumerate(gold):
                    f = self.features(text, at, past)
                    if (sum(w.get(x, 0.0) for x in f) > 0) != (y == 1):
                        d = 1.0 if y == 1 else -1.0
                        for x in f:
                            w[x] = w.get(x, 0.0) + d
                            total[x] = total.get(x, 0.0) + d * step
                    step += 1
                    past = (y, past[0])
        self.weights = {x: v - total[x] / step for x, v in w.items()}
        return self

    def __call__(self, texts: list[str]) -> list[list[int]]:
        out = []
        for t in texts:
            a, past = [], (2, 2)
            for at in range(len(t)):
                y = int(at > 0 and sum(self.weights.get(x, 0.0) for x in self.features(t, at, past)) > 0)
                a.append(y)
                past = (y, past[0])
            out.append(a)
        return out
