"""Baseline: a deep recurrent network that reads bytes and writes labelled spans.

A segment of at most SEGMENT bytes (whole tokens) is read backwards by a stack of
gated recurrent layers; after a start mark the same stack writes, for each token in
order, its first byte, its length and its label, and then a stop mark. Nothing but
byte values and spans is known to the network; tokens are its output.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import cost

SEGMENT = 60


def segments(toks: list[str]) -> Iterator[tuple[bytes, int, int]]:
    """(bytes, first token, end) of successive runs of whole tokens, a blank byte between them; a longer token is cut at SEGMENT bytes."""
    held, start = b"", 0
    for i, t in enumerate(toks):
        raw = t.encode("utf-8", "surrogatepass")
        if held and len(held) + 1 + len(raw) > SEGMENT:
            yield held, start, i
            held, start = b"", i
        held = held + b" " + raw if held else raw[:SEGMENT]
    if held:
        yield held, start, len(toks)


def gold_spans(toks: list[str], tags: list[str]) -> list[tuple[int, int, str]]:
    out, at = [], 0
    for t, tag in zip(toks, tags, strict=True):
        n = min(len(t.encode("utf-8", "surrogatepass")), SEGMENT)
        out.append((at, n, tag))
        at += n + 1
    return out


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -30, 30)))


class ByteSpanNetwork:
    """``layers`` recurrent layers of ``width``; symbols are bytes, then starts, lengths, labels, the stop and the start mark."""

    def __init__(self, labels: list[str], width: int = 32, layers: int = 4, seed: int = 1, dtype=np.float32):
        rng = np.random.default_rng(seed)
        self.labels, self.width, self.layers = list(labels), width, layers
        self.outputs = 2 * SEGMENT + len(labels) + 1
        self.stop, self.go = self.outputs - 1, 256 + self.outputs
        draw = lambda *shape: (rng.normal(0, 1 / np.sqrt(shape[-1]), shape)).astype(dtype)
        self.table, self.out, self.bias = draw(257 + self.outputs, width), draw(self.outputs, width), np.zeros(self.outputs, dtype)
        self.wx, self.wh, self.b = [draw(4 * width, width) for _ in range(layers)], [draw(4 * width, width) for _ in range(layers)], [np.zeros(4 * width, dtype) for _ in range(layers)]
        for b in self.b:
            b[width : 2 * width] = 1  # memory is kept at first

    def parameters(self) -> list[np.ndarray]:
        return [self.table, self.out, self.bias, *self.wx, *self.wh, *self.b]

    @property
    def size(self) -> int:
        return sum(p.size for p in self.parameters())

    def flops(self, steps: float) -> float:
        """Operations of the recurrent layers over ``steps`` bytes and symbols."""
        return cost.lstm_flops(self.layers, self.width) * steps

    def symbols(self, spans: list[tuple[int, int, str]]) -> list[int]:
        number = {x: i for i, x in enumerate(self.labels)}
        return [s for a, n, tag in spans for s in (a, SEGMENT + n - 1, 2 * SEGMENT + number[tag])] + [self.stop]

    def _step(self, x: np.ndarray, state: list, keep: np.ndarray | None, caches: list | None) -> np.ndarray:
        w = self.width
        for k in range(self.layers):
            h, c = state[k]
            z = x @ self.wx[k].T + h @ self.wh[k].T + self.b[k]
            i, f, o = _sigmoid(z[:, :w]), _sigmoid(z[:, w : 2 * w]), _sigmoid(z[:, 3 * w :])
            g = np.tanh(z[:, 2 * w : 3 * w])
            new = f * c + i * g
            t = np.tanh(new)
            made = o * t
            if keep is not None:
                new, made = new * keep, made * keep
            if caches is not None:
                caches.append((x, h, c, i, f, g, o, t))
            state[k] = (made, new)
            x = made
        return x

    def batch(self, texts: list[bytes], spans: list | None) -> tuple[np.ndarray, np.ndarray, int]:
        """Inputs (right-aligned bytes backwards, the start mark, then what is written) and targets; -1 is padding."""
        read = max(map(len, texts))
        wrote = [self.symbols(s) for s in spans] if spans else [[] for _ in texts]
        x = np.full((len(texts), read + max(1, max(map(len, wrote)))), -1)
        y = np.full(x.shape, -1)
        for r, (t, w) in enumerate(zip(texts, wrote, strict=True)):
            x[r, read - len(t) : read] = list(reversed(t))
            x[r, read] = self.go
            if w:
                x[r, read + 1 : read + len(w)] = np.array(w[:-1]) + 256
                y[r, read : read + len(w)] = w
        return x, y, read

    def loss_and_grad(self, texts: list[bytes], spans: list) -> tuple[float, list[np.ndarray]]:
        """Mean cross-entropy of the written symbols and its gradients, back through all steps."""
        x, y, read = self.batch(texts, spans)
        n, steps = x.shape
        zero = np.zeros((n, self.width), self.table.dtype)
        state, caches, tops, keeps = [(zero, zero)] * self.layers, [], [], (x >= 0).astype(self.table.dtype)
        for s in range(steps):
            tops.append(self._step(self.table[x[:, s]], state, keeps[:, s : s + 1], caches))
        total, grads = max(1, int((y >= 0).sum())), [np.zeros_like(p) for p in self.parameters()]
        d_table, d_out, d_bias = grads[:3]
        d_wx, d_wh, d_b = grads[3 : 3 + self.layers], grads[3 + self.layers : 3 + 2 * self.layers], grads[3 + 2 * self.layers :]
        loss, dh, dc = 0.0, [zero.copy() for _ in range(self.layers)], [zero.copy() for _ in range(self.layers)]
        for s in reversed(range(steps)):
            d = np.zeros_like(zero)
            rows = np.flatnonzero(y[:, s] >= 0) if s >= read else []
            if len(rows):
                top = tops[s][rows]
                z = top @ self.out.T + self.bias
                z -= z.max(1, keepdims=True)
                p = np.exp(z)
                p /= p.sum(1, keepdims=True)
                loss -= float(np.log(np.maximum(p[np.arange(len(rows)), y[rows, s]], 1e-12)).sum())
                p[np.arange(len(rows)), y[rows, s]] -= 1
                p /= total
                d_out += p.T @ top
                d_bias += p.sum(0)
                d[rows] = p @ self.out
            for k in reversed(range(self.layers)):
                u, h, c, i, f, g, o, t = caches[s * self.layers + k]
                made = (dh[k] + d) * keeps[:, s : s + 1]
                cell = dc[k] * keeps[:, s : s + 1] + made * o * (1 - t * t)
                gates = np.concatenate([cell * g * i * (1 - i), cell * c * f * (1 - f), cell * i * (1 - g * g), made * t * o * (1 - o)], 1)
                d_wx[k] += gates.T @ u
                d_wh[k] += gates.T @ h
                d_b[k] += gates.sum(0)
                dh[k], dc[k], d = gates @ self.wh[k], cell * f, gates @ self.wx[k]
            live = x[:, s] >= 0
            np.add.at(d_table, x[live, s], d[live])
        return loss / total, grads

    def fit(self, data: list[tuple[bytes, list]], epochs: int = 4, size: int = 32, rate: float = 4e-3, seed: int = 1) -> ByteSpanNetwork:
        """Steps of adaptive moments over segments of like length."""
        rng, step = np.random.default_rng(seed), 0
        params = self.parameters()
        first, second = [np.zeros_like(p) for p in params], [np.zeros_like(p) for p in params]
        order = sorted(range(len(data)), key=lambda r: len(data[r][0]))
        parts = [order[a : a + size] for a in range(0, len(order), size)]
        for _ in range(epochs):
            for at in rng.permutation(len(parts)):
                _, grads = self.loss_and_grad([data[r][0] for r in parts[at]], [data[r][1] for r in parts[at]])
                step += 1
                norm = np.sqrt(sum(float((g * g).sum()) for g in grads))
                for p, g, m, v in zip(params, grads, first, second, strict=True):
                    g = g * min(1.0, 1.0 / (norm + 1e-9))
                    m += 0.1 * (g - m)
                    v += 0.001 * (g * g - v)
                    p -= (rate * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.999**step)) + 1e-8)).astype(p.dtype)
        return self

    def write(self, texts: list[bytes]) -> list[set]:
        """The spans written for each segment, most likely symbol by symbol among those that may come next."""
        x, _, read = self.batch(texts, None)
        zero = np.zeros((len(texts), self.width), self.table.dtype)
        state = [(zero, zero)] * self.layers
        for s in range(read):
            self._step(self.table[x[:, s]], state, (x[:, s : s + 1] >= 0).astype(zero.dtype), None)
        out, live, now = np.full((len(texts), 3 * SEGMENT), -1), np.arange(len(texts)), x[:, read]
        turns = ((0, SEGMENT), (SEGMENT, 2 * SEGMENT), (2 * SEGMENT, self.stop))
        for t in range(3 * SEGMENT):
            z = self._step(self.table[now], state, None, None) @ self.out.T + self.bias
            lo, hi = turns[t % 3]
            best = lo + z[:, lo:hi].argmax(1)
            if t % 3 == 0:
                goes = z[:, self.stop] <= z[np.arange(len(z)), best]
                if not goes.all():  # segments that have stopped take no more steps
                    live, best, state = live[goes], best[goes], [(h[goes], c[goes]) for h, c in state]
                if not len(live):
                    break
            out[live, t] = best
            now = best + 256
        out = [w[w >= 0].tolist() for w in out]
        return [{(a, n - SEGMENT + 1, self.labels[tag - 2 * SEGMENT]) for a, n, tag in zip(w[::3], w[1::3], w[2::3], strict=False)} for w in out]


def training_data(rows: list[dict]) -> list[tuple[bytes, list]]:
    return [(text, gold_spans(r["toks"][a:b], r["tags"][a:b])) for r in rows for text, a, b in segments(r["toks"])]


def evaluate(sents: DataFrame, net: ByteSpanNetwork) -> DataFrame:
    """(lang, tokens, right, steps): tokens whose span and label were written, and bytes and symbols that were read and written."""
    held = sents.sparkSession.sparkContext.broadcast(net)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            every = [(lang, text, gold_spans(list(toks[a:b]), list(tags[a:b]))) for lang, toks, tags in zip(batch["lang"], batch["toks"], batch["tags"], strict=True) for text, a, b in segments(list(toks))]
            every.sort(key=lambda x: len(x[1]))
            for a in range(0, len(every), 512):
                part = every[a : a + 512]
                wrote = held.value.write([text for _, text, _ in part])
                rows = [(lang, len(gold), len(w & set(gold)), len(text) + 3 * len(gold) + 1) for (lang, text, gold), w in zip(part, wrote, strict=True)]
                yield pd.DataFrame(rows, columns=["lang", "tokens", "right", "steps"]).groupby("lang", as_index=False).sum()

    made = sents.select("lang", "toks", "tags").mapInPandas(run, "lang string, tokens long, right long, steps long")
    return made.groupBy("lang").agg(*[F.sum(c).alias(c) for c in ("tokens", "right", "steps")])
