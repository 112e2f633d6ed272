"""Preordering by a transition system over spans of words.

State: a stack and a buffer of spans. SHIFT moves the buffer's head to the stack;
APPEND joins the two top spans; SWAP returns the second span to the buffer's head
and is legal only while its key stands before the top's in the source. Joined spans
give up a key for good, so every pair of keys swaps at most once and every
derivation ends. A span's key is the source place of its leading word, or (option)
of its last word or of the word that stands first in the source.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import gram_bags
from . import train
from .features import FeatureGroup, Template
from .model import Network
from .postag import TAGS, end_bags
from .train import Bags

SHIFT, APPEND, SWAP = 0, 1, 2
ACTIONS = ["SHIFT", "APPEND", "SWAP"]


@dataclass(slots=True)
class Span:
    """Words in target order, linked from ``first`` to ``last``; ``low`` stands first in the source."""

    first: int
    last: int
    low: int
    size: int = 1


KEYS = {"first": lambda x: x.first, "last": lambda x: x.last, "min": lambda x: x.low}


class TransitionSystem:
    def __init__(self, n: int, key: str = "first"):
        self.stack: list[Span] = []
        self.buffer = [Span(i, i, i) for i in range(n - 1, -1, -1)]  # the head is last
        self.follow, self.key = [-1] * n, KEYS[key]
        self.swaps = self.steps = 0

    def legal(self) -> list[int]:
        two = len(self.stack) > 1
        return [SHIFT] * bool(self.buffer) + [APPEND] * two + [SWAP] * (two and self.key(self.stack[-2]) < self.key(self.stack[-1]))

    def apply(self, action: int) -> None:
        if action not in self.legal():
            raise ValueError(f"{ACTIONS[action]} is not legal here")
        if action == SHIFT:
            self.stack.append(self.buffer.pop())
        elif action == APPEND:
            top, second = self.stack.pop(), self.stack.pop()
            self.follow[second.last] = top.first
            self.stack.append(Span(second.first, top.last, min(second.low, top.low), second.size + top.size))
        else:
            self.buffer.append(self.stack.pop(-2))
            self.swaps += 1
        self.steps += 1

    @property
    def done(self) -> bool:
        return not self.buffer and len(self.stack) <= 1

    @property
    def order(self) -> list[int]:
        out, at = [], self.stack[0].first if self.stack else -1
        while at >= 0:
            out.append(at)
            at = self.follow[at]
        return out


def derivation(rank: list[int], eager: bool = True, key: str = "first") -> list[int]:
    """Actions that bring words into target order; ``rank[i]``: target place of word i. Eager joins neighbours at once."""
    s, out = TransitionSystem(len(rank), key), []
    while not s.done:
        a = SHIFT
        if len(s.stack) > 1:
            second, top = s.stack[-2], s.stack[-1]
            if rank[second.first] > rank[top.first]:
                a = SWAP
            elif (eager or not s.buffer) and rank[second.last] + 1 == rank[top.first]:
                a = APPEND
        s.apply(a)
        out.append(a)
    return out


#: Fixed class ranks of the head-final target order.
CLASS_RANK = {"PROPN": 0, "NOUN": 0, "ADJ": 0, "NUM": 1, "SYM": 1, "ADV": 1, "FUNC": 2, "VERB": 3}


def silver_order(tags: list[str]) -> list[int]:
    """Target rank of every word: inside a clause (ended by punctuation) a stable sort by class, punctuation last."""
    clause, keys = 0, []
    for i, t in enumerate(tags):
        keys.append((clause, 4 if t == "PUNCT" else CLASS_RANK[t], i))
        clause += t == "PUNCT"
    rank = [0] * len(tags)
    for r, (_, _, i) in enumerate(sorted(keys)):
        rank[i] = r
    return rank


def silver_ranks(batch: pa.RecordBatch) -> pa.ListArray:
    """``silver_order`` of the tags of every row (column ``tags``), all rows at once."""
    tags, size = batch.column("tags").flatten().dictionary_encode(), np.diff(batch.column("tags").offsets.to_numpy())
    kind = np.array([4 if t == "PUNCT" else CLASS_RANK[t] for t in tags.dictionary.to_pylist()], np.int64)[tags.indices.to_numpy()]
    start = np.append(0, np.cumsum(size))
    ends = np.append(0, np.cumsum(kind == 4))
    row = np.repeat(np.arange(len(size)), size)
    key = ((ends[:-1] + row) << 3) + kind  # clauses in order; those of another row never meet
    rank = np.empty(len(kind), np.int32)
    rank[np.argsort(key, kind="stable")] = np.arange(len(kind)) - start[row]
    return pa.ListArray.from_arrays(pa.array(start.astype(np.int32)), pa.array(rank))


PLACES = 6  # top span's first and last word, second span's first and last word, buffer head, and the one after


def template(kind: str = "words", dim: int = 8) -> Template:
    groups = [FeatureGroup("ends", 1000, dim, slots=PLACES, kind="affix"), FeatureGroup("state", 16, 4, slots=2, kind="state")]
    if kind == "tags":
        groups.append(FeatureGroup("tags", len(TAGS) + 1, 6, slots=PLACES, kind="tag"))
    if kind == "tagger_inputs":
        groups += [FeatureGroup("bigrams", 1000, dim, slots=3 * PLACES, n=2), FeatureGroup("trigrams", 2000, dim, slots=PLACES, n=3)]
    return Template(tuple(groups))


def _groups(t: Template) -> list[int]:
    return [i for i, g in enumerate(t.groups) for _ in range(g.slots)]


class Sentences:
    """The words of many sentences: features of distinct words once, and for each token its word and tag.

    Tokens are numbered through; -1 stands outside every sentence.
    """

    def __init__(self, toks: list[list[str]], tags: list[list[str]] | None, t: Template, kind: str):
        size = np.fromiter(map(len, toks), np.int64, len(toks))
        self.start = np.append(0, np.cumsum(size))
        flat = np.empty(int(size.sum()) + 1, object)
        flat[0], flat[1:] = "\x00", [w.lower() for x in toks for w in x]
        at, words = pd.factorize(flat)
        self.word = np.append(at[1:], 0)  # the last is read by -1
        self.first, self.last = (np.zeros(len(self.word), bool) for _ in range(2))
        self.first[self.start[:-1][size > 0]] = self.last[self.start[1:][size > 0] - 1] = True
        v = [g.vocab for g in t.groups]
        ends = [end_bags(["^" + w[:3] for w in words], v[0])[0], end_bags([w[-3:] + "$" for w in words], v[0])[0]]
        self.tables = [(0, np.stack(ends, 1).ravel(), 2 * np.arange(len(words) + 1))]
        if kind == "tags":
            number = {x: i for i, x in enumerate(TAGS, 1)}
            self.tag = np.array([number[x] for s in tags for x in s] + [0])
            self.tables.append((2, np.arange(len(TAGS) + 1), np.arange(len(TAGS) + 2)))
        if kind == "tagger_inputs":
            wrapped = [f"^{w}$" for w in words]
            self.tables += [(g, *gram_bags(wrapped, n, v[g])) for g, n in ((2, 2), (3, 3))]
        self.kind = kind
        more = {"tags": [1], "tagger_inputs": [3, 1]}.get(kind, [])
        self.place = [p for many in [1, *more] for p in range(PLACES) for _ in range(many)]  # of each slot

    def slots(self, places: np.ndarray) -> list[tuple[int, np.ndarray]]:
        """(table, row) of every slot but those of the state; ``places``: (states, PLACES) tokens."""
        out = [(0, self.word[p]) for p in places.T]
        if self.kind == "tags":
            out += [(1, self.tag[p]) for p in places.T]
        if self.kind == "tagger_inputs":
            for p in places.T:
                near = (np.where((p < 0) | self.first[p], -1, p - 1), p, np.where((p < 0) | self.last[p], -1, p + 1))
                out += [(1, self.word[q]) for q in near]
            out += [(2, self.word[p]) for p in places.T]
        return out

    def state_bags(self, t: Template, places: np.ndarray, states: np.ndarray) -> Bags:
        one, parts = np.arange(len(places) + 1), []
        for table, row in self.slots(places):
            g, ids, off = self.tables[table]
            made = Bags([g], [ids], [off]).take(row)
            parts.append((made.ids[0], made.offsets[0]))
        parts[PLACES:PLACES] = [(s, one) for s in states.T]
        return Bags(_groups(t), [i for i, _ in parts], [o for _, o in parts])


class Scorer:
    """Action scores of many states: each place's share in the hidden layer is computed once for every token."""

    def __init__(self, net: Network, words: Sentences):
        self.net = net
        dims = [net.template.groups[g].dim for g in _groups(net.template)]
        stop = np.cumsum(dims)
        weight = [net.w[:, b - d : b].T for d, b in zip(dims, stop, strict=True)]
        rows = [train.embed(net, Bags([g], [ids], [off])) for g, ids, off in words.tables]
        state = net.rows(1, np.arange(net.template.groups[1].vocab))
        self.state = [state @ w for w in weight[PLACES : PLACES + 2]]
        tokens = np.append(np.arange(len(words.word) - 1), -1)  # the last row is read by -1
        slots = words.slots(np.repeat(tokens[:, None], PLACES, 1))
        self.shares = np.zeros((PLACES, len(tokens), len(net.c)), np.float32)
        for i, ((table, row), w) in enumerate(zip(slots, weight[:PLACES] + weight[PLACES + 2 :], strict=True)):
            self.shares[words.place[i]] += (rows[table] @ w)[row]

    def __call__(self, places: np.ndarray, states: np.ndarray) -> np.ndarray:
        hidden = self.state[0][states[:, 0]]
        hidden += self.state[1][states[:, 1]]
        hidden += self.net.c
        for share, at in zip(self.shares, places.T, strict=True):
            hidden += share[at]
        return np.maximum(hidden, 0, out=hidden) @ self.net.beta.T + self.net.b

    def alone(self):
        """A function of one state's places and state features: its scores as a list, by the same sums in the same order."""
        state = self.state[0][:, None] + self.state[1][None]
        state += self.net.c
        shares, beta, b, relu = self.shares, np.ascontiguousarray(self.net.beta.T), self.net.b, np.maximum

        def score(places: tuple[int, ...], held: int, size: int) -> list[float]:
            hidden = state[held, size].copy()
            for k, at in enumerate(places):
                hidden += shares[k, at]
            return (relu(hidden, 0, out=hidden) @ beta + b).tolist()

        return score


def _seen(s: TransitionSystem, start: int) -> tuple[list[int], list[int]]:
    """The tokens at the PLACES of a state (from ``start`` on), and its two state features."""
    top, second = (s.stack[-1] if s.stack else None), (s.stack[-2] if len(s.stack) > 1 else None)
    ends = lambda x: [start + x.first, start + x.last] if x else [-1, -1]
    ahead = [start + s.buffer[-1].first if s.buffer else -1, start + s.buffer[-2].first if len(s.buffer) > 1 else -1]
    swap = bool(top and second and s.key(second) < s.key(top))
    return ends(top) + ends(second) + ahead, [min(3, len(s.stack)) * 4 + min(3, len(s.buffer)), swap * 8 + min(7, top.size if top else 0)]


def gold_data(rows: list[dict], t: Template, kind: str) -> tuple[Bags, np.ndarray]:
    """States and actions of the eager derivations; ``tags`` are those the model will see (predicted ones)."""
    words = Sentences([r["toks"] for r in rows], [r["tags"] for r in rows], t, kind)
    places, states, y = [], [], []
    for r, start in zip(rows, words.start.tolist(), strict=False):
        s = TransitionSystem(len(r["toks"]))
        for a in derivation(r["rank"]):
            p, f = _seen(s, start)
            places.append(p)
            states.append(f)
            y.append(a)
            s.apply(a)
    return words.state_bags(t, np.array(places), np.array(states)), np.array(y)


def score_of(dev: list[dict]):
    """The task's measure: mean score of decoded held-out sentences."""

    def score(net: Network, _) -> float:
        orders = decode([r["toks"] for r in dev], [r["tags"] for r in dev], net)[0]
        return float(np.mean([frs([r["rank"][i] for i in o]) for r, o in zip(dev, orders, strict=True)]))

    return score


def start(kind: str = "words", hidden: int = 48, seed: int = 0) -> Network:
    net = Network.random(template(kind), hidden, ACTIONS, seed=len(kind) + seed)
    net.resources["kind"] = kind
    return net


def build(rows: list[dict], dev: list[dict], kind: str = "words", hidden: int = 48, epochs: int = 2, seed: int = 0) -> Network:
    """Learns from sentences (``toks``, ``tags``, ``rank``); training stops early by the score of decoded held-out sentences."""
    net = start(kind, hidden, seed)
    settings = train.Settings(lr=0.1, epochs=epochs, seed=1 + seed)
    net, _ = train.sgd(net, *gold_data(rows, net.template, kind), settings, gold_data(dev, net.template, kind), every=500, metric=score_of(dev))
    return net


#: Tokens of sentences that are decoded together, the number of unfinished ones from which each goes on alone, and the
#: states of a repeated action that are scored together.
BLOCK_TOKENS, FEW, RUN = 1 << 16, 12, 512


class States:
    """The transition systems (of key ``first``) of many sentences as arrays: a span is known by its first word.

    Stacks and buffers lie side by side in one array each, at the places of their sentences' tokens; no stack and
    no buffer is longer than its sentence. A buffer's head is its last place.
    """

    def __init__(self, start: np.ndarray):
        n = int(start[-1])
        self.base, self.held, self.left = start[:-1], np.zeros(len(start) - 1, np.int64), np.diff(start)
        self.stack = np.zeros(n + 2, np.int64)
        self.buffer = np.append(np.repeat(start[1:] + start[:-1] - 1, self.left) - np.arange(n), [0, 0])
        self.last, self.size, self.follow = np.arange(n), np.ones(n, np.int64), np.full(n, -1)
        self.steps = self.swaps = 0

    @property
    def live(self) -> np.ndarray:
        return np.flatnonzero((self.left > 0) | (self.held > 1))

    def step(self, who: np.ndarray, scorer: Scorer) -> np.ndarray:
        """Takes the best legal action of the sentences ``who``, and returns those that are not done."""
        base, held, left = self.base[who], self.held[who], self.left[who]
        two = held > 1
        top, second = np.where(held > 0, self.stack[base + held - 1], -1), np.where(two, self.stack[base + held - 2], -1)
        head, ahead = np.where(left > 0, self.buffer[base + left - 1], -1), np.where(left > 1, self.buffer[base + left - 2], -1)
        swap = two & (second < top)
        ends = [np.where(x < 0, -1, self.last[x]) for x in (top, second)]
        size = np.where(top < 0, 0, np.minimum(7, self.size[top]))
        states = np.stack([np.minimum(3, held) * 4 + np.minimum(3, left), swap * 8 + size], 1)
        scores = scorer(np.stack([top, ends[0], second, ends[1], head, ahead], 1), states)
        scores[~np.stack([left > 0, two, swap], 1)] = -np.inf
        action = scores.argmax(1)
        shift, join, swapped = (np.flatnonzero(action == a) for a in (SHIFT, APPEND, SWAP))
        self.stack[base[shift] + held[shift]] = head[shift]
        a, b = second[join], top[join]
        self.follow[self.last[a]] = b
        self.last[a] = self.last[b]
        self.size[a] += self.size[b]
        self.buffer[base[swapped] + left[swapped]] = second[swapped]
        self.stack[base[swapped] + held[swapped] - 2] = top[swapped]
        held = held + np.array([1, -1, -1])[action]
        left = left + np.array([-1, 0, 1])[action]
        self.held[who], self.left[who] = held, left
        self.steps += len(who)
        self.swaps += len(swapped)
        return who[(left > 0) | (held > 1)]

    def finish(self, i: int, scorer: Scorer) -> None:
        """All remaining steps of one sentence, by the same rules as ``step``: a pass over arrays costs more than a few states are worth.

        While an action repeats, the states of further repetitions are known and scored together; those up to the
        first other action are taken. So the many swaps of a long sentence are not single steps.
        """
        base, score = int(self.base[i]), scorer.alone()
        end = int(self.base[i + 1]) if i + 1 < len(self.base) else len(self.last)
        stack, buffer = (x[base : base + int(n)].tolist() for x, n in ((self.stack, self.held[i]), (self.buffer, self.left[i])))
        last, size, follow = (x[base:end].tolist() for x in (self.last, self.size, self.follow))
        before, same = -1, 0
        while buffer or len(stack) > 1:
            held, left = len(stack), len(buffer)
            top, second = stack[-1] if held else -1, stack[-2] if held > 1 else -1
            head, ahead = buffer[-1] if left else -1, buffer[-2] if left > 1 else -1
            if same > 1 and before != APPEND and (held > 2 if before == SWAP else left > 1):
                k = min(RUN, 4 * same, held - 1 if before == SWAP else left)
                if before == SWAP:
                    moved = stack[held - 1 - k : held - 1][::-1]
                    tops, seconds, heads, aheads = [top] * k, moved, [head, *moved][:k], [ahead, head, *moved][:k]
                else:
                    moved = buffer[left - k :][::-1]
                    tops, seconds, heads, aheads = [top, *moved][:k], [second, top, *moved][:k], moved, [*moved[1:], buffer[left - k - 1] if left > k else -1]
                best = self._repeated(scorer, before, held, left, [tops, seconds, heads, aheads], [[-1 if x < 0 else last[x - base] for x in y] for y in (tops, seconds)], [0 if x < 0 else size[x - base] for x in tops])
                other = np.flatnonzero(best != before)
                many = int(other[0]) if len(other) else k
                if before == SWAP:
                    buffer += moved[:many]
                    del stack[held - 1 - many : held - 1]
                    self.swaps += many
                else:
                    stack += moved[:many]
                    del buffer[left - many :]
                self.steps += many
                same += many
                if many == k:
                    continue
                action = int(best[many])
            else:
                two = held > 1
                swap = two and second < top
                places = (top, last[top - base] if held else -1, second, last[second - base] if two else -1, head, ahead)
                got = score(places, min(3, held) * 4 + min(3, left), swap * 8 + (min(7, size[top - base]) if held else 0))
                action = max((a for a, legal in ((SHIFT, left), (APPEND, two), (SWAP, swap)) if legal), key=got.__getitem__)  # the first of equal ones
            if action == SHIFT:
                stack.append(buffer.pop())
            elif action == APPEND:
                b, a = stack.pop(), stack[-1]
                follow[last[a - base] - base] = b
                last[a - base] = last[b - base]
                size[a - base] += size[b - base]
            else:
                buffer.append(stack.pop(-2))
                self.swaps += 1
            self.steps += 1
            before, same = action, same + 1 if action == before else 1
        self.follow[base:end] = follow
        self.stack[base : base + len(stack)] = stack
        self.held[i], self.left[i] = len(stack), 0

    @staticmethod
    def _repeated(scorer: Scorer, action: int, held: int, left: int, seen: list[list[int]], ends: list[list[int]], size: list[int]) -> np.ndarray:
        """The best legal action in each of the states that follow one another if ``action`` is taken again and again."""
        top, second, head, ahead = np.array(seen)
        step = np.arange(len(top)) * (-1 if action == SWAP else 1)
        held, left = held + step, left - step
        two = held > 1
        swap = two & (second < top)
        states = np.stack([np.minimum(3, held) * 4 + np.minimum(3, left), swap * 8 + np.minimum(7, size)], 1)
        scores = scorer(np.stack([top, np.array(ends[0]), second, np.array(ends[1]), head, ahead], 1), states)
        scores[~np.stack([left > 0, two, swap], 1)] = -np.inf
        return scores.argmax(1)

    def orders(self) -> list[list[int]]:
        follow, out = self.follow.tolist(), []
        for begin, first, held in zip(self.base.tolist(), self.stack[self.base].tolist(), self.held.tolist(), strict=True):
            order, at = [], first if held else -1
            while at >= 0:
                order.append(at - begin)
                at = follow[at]
            out.append(order)
        return out


def decode(toks: list[list[str]], tags: list[list[str]] | None, net: Network) -> tuple[list[list[int]], int, int]:
    """Orders of all sentences, in lock step: one pass over the unfinished ones a step; also steps and swaps.

    Sentences of about equal lengths go together, the longest first; the last few of them go on one by one.
    """
    size = np.fromiter(map(len, toks), np.int64, len(toks))
    by_size, orders, steps, swaps = np.argsort(-size, kind="stable"), [[] for _ in toks], 0, 0
    for mine in np.split(by_size, np.flatnonzero(np.diff(np.cumsum(size[by_size]) // BLOCK_TOKENS)) + 1):
        if not len(mine):
            continue
        words = Sentences([toks[i] for i in mine], tags and [tags[i] for i in mine], net.template, net.resources["kind"])
        scorer, states = Scorer(net, words), States(words.start)
        live = states.live
        while len(live) > FEW:
            live = states.step(live, scorer)
        for i in live.tolist():
            states.finish(i, scorer)
        for i, order in zip(mine.tolist(), states.orders(), strict=True):
            orders[i] = order
        steps, swaps = steps + states.steps, swaps + states.swaps
    return orders, steps, swaps


def frs(rank_in_order: list[int]) -> float:
    full = [-1, *rank_in_order, len(rank_in_order)]
    return 100.0 * sum(b == a + 1 for a, b in zip(full, full[1:], strict=False)) / (len(full) - 1)


def evaluate(sents: DataFrame, nets: dict, tag_column: str = "tags") -> DataFrame:
    """Mean score and share of exact orders of every named model by one Arrow pass over sentences of any length.

    A model is a network, a function from tags to an order, or identity, reverse or rule (the rule order of the tags given).
    """
    held = sents.sparkSession.sparkContext.broadcast(nets)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            if len(batch):
                toks, tags, ranks = ([x.tolist() for x in batch[c]] for c in ("toks", tag_column, "rank"))
                for name, net in held.value.items():
                    if net == "rule":
                        orders = [np.argsort(silver_order(x)).tolist() for x in tags]
                    elif isinstance(net, str):
                        orders = [list(range(len(x)))[:: -1 if net == "reverse" else 1] for x in toks]
                    elif isinstance(net, BracketPreorderer):
                        orders = net.orders(tags)
                    elif callable(net):
                        orders = [net(x) for x in tags]
                    else:
                        orders = decode(toks, tags, net)[0]
                    made = [[r[i] for i in o] for r, o in zip(ranks, orders, strict=True)]
                    yield pd.DataFrame({"model": [name], "sentences": [len(toks)], "total": [sum(map(frs, made))], "exact": [sum(m == sorted(m) for m in made)]})

    out = sents.select(*dict.fromkeys(["toks", tag_column, "rank"])).mapInPandas(run, "model string, sentences long, total double, exact long")
    return out.groupBy("model").agg(F.sum("sentences").alias("sentences"), (F.sum("total") / F.sum("sentences")).alias("frs"), (F.sum("exact") / F.sum("sentences")).alias("exact"))


class BracketPreorderer:
    """Binary bracketing baseline: a chart over spans decides, by tag-pair weights, which neighbours are inverted.

    The weights are those of an averaged perceptron. The chart takes the cube of the length, so a
    sentence of more than ``longest`` tokens keeps its order.
    """

    def __init__(self, longest: int = 40):
        self.weights: dict[tuple[str, str], float] = {}
        self.longest = longest

    def fit(self, rows: list[dict], epochs: int = 2) -> BracketPreorderer:
        total, step = {}, 1
        for _ in range(epochs):
            for r in rows:
                if not 1 < len(r["tags"]) <= self.longest:
                    continue
                place = np.argsort(self(r["tags"]))
                for j, b in enumerate(r["tags"]):
                    for i, a in enumerate(r["tags"][:j]):
                        kept = r["rank"][i] < r["rank"][j]
                        if kept != (place[i] < place[j]):
                            d = 1.0 if kept else -1.0
                            self.weights[a, b] = self.weights.get((a, b), 0.0) + d
                            total[a, b] = total.get((a, b), 0.0) + d * step
                step += 1
        self.weights = {pair: v - total[pair] / step for pair, v in self.weights.items()}
        return self

    def __call__(self, tags: list[str]) -> list[int]:
        return self.orders([tags])[0]

    def orders(self, sents: list[list[str]], cells: int = 1 << 18) -> list[list[int]]:
        """Orders of many sentences; the charts of those of one length (about ``cells`` cells of them) are filled together."""
        names = sorted({t for x in sents for t in x})
        number = {t: i for i, t in enumerate(names)}
        pair = np.array([[self.weights.get((a, b), 0.1) for b in names] for a in names])
        out, by_length = [list(range(len(x))) for x in sents], {}
        for i, x in enumerate(sents):
            if 2 <= len(x) <= self.longest:
                by_length.setdefault(len(x), []).append(i)
        for n, mine in by_length.items():
            step = max(1, cells // (n + 1) ** 2)
            for k in range(0, len(mine), step):
                at = np.array([[number[t] for t in sents[i]] for i in mine[k : k + step]])
                cut, inverted = self._charts(pair[at[:, :, None], at[:, None, :]])
                for i, c, v in zip(mine[k : k + step], cut.tolist(), inverted.tolist(), strict=True):
                    out[i] = self._read(c, v, n)
        return out

    @staticmethod
    def _charts(keep: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """For each sentence and span [a, b): where it is cut, and whether its parts change places."""
        many, n = keep.shape[:2]
        total = np.zeros((many, n + 1, n + 1))
        total[:, 1:, 1:] = np.cumsum(np.cumsum(keep, 1), 2)
        best, cut, inverted = np.zeros((many, n + 1, n + 1)), np.zeros((many, n + 1, n + 1), np.int64), np.zeros((many, n + 1, n + 1), bool)
        rows = np.arange(many)[:, None]
        for size in range(2, n + 1):
            a = np.arange(n - size + 1)
            b, m = a + size, a[:, None] + np.arange(1, size)
            left, right = a[:, None], b[:, None]
            cross = total[:, m, right] - total[:, left, right] - total[:, m, m] + total[:, left, m]  # pairs of a left and a right word
            value = best[:, left, m] + best[:, m, right] + np.abs(cross)
            k = value.argmax(2)
            best[:, a, b], cut[:, a, b] = value[rows, np.arange(len(a)), k], a + 1 + k
            inverted[:, a, b] = cross[rows, np.arange(len(a)), k] < 0
        return cut, inverted

    @staticmethod
    def _read(cut: list, inverted: list, n: int) -> list[int]:
        out, spans = [], [(0, n)]
        while spans:
            a, b = spans.pop()
            if b - a == 1:
                out.append(a)
                continue
            m = cut[a][b]
            spans += [(a, m), (m, b)] if inverted[a][b] else [(m, b), (a, m)]
        return out
