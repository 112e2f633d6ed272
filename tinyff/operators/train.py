"""Training of the small network: mini-batch SGD with momentum, decaying rate, averaging, early stopping.

Steps are sequential, so one task trains one model; Spark runs the trials of a grid
side by side over one broadcast sample of bounded size, or (``local_sgd``) trains on
all partitions and averages parameters by rounds.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass, replace

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .model import Network


@dataclass
class Bags:
    """Features of n rows: for every slot its group, and a non-empty bag of ids per row (CSR)."""

    groups: list[int]
    ids: list[np.ndarray]
    offsets: list[np.ndarray]

    def __len__(self) -> int:
        return len(self.offsets[0]) - 1

    @staticmethod
    def of(groups: list[int], rows: list[list[np.ndarray]]) -> Bags:
        """``rows[r][s]``: ids of slot s in row r; an empty bag becomes the single id 0."""
        ids, offsets = [], []
        for s in range(len(groups)):
            bags = [r[s] if len(r[s]) else np.zeros(1, np.int32) for r in rows]
            ids.append(np.concatenate(bags).astype(np.int64) if bags else np.zeros(0, np.int64))
            offsets.append(np.append(0, np.cumsum([len(b) for b in bags])).astype(np.int64))
        return Bags(list(groups), ids, offsets)

    def take(self, rows: np.ndarray) -> Bags:
        ids, offsets = [], []
        for i, o in zip(self.ids, self.offsets, strict=True):
            n = o[rows + 1] - o[rows]
            end = np.cumsum(n)
            ids.append(i[np.repeat(o[rows], n) + np.arange(n.sum()) - np.repeat(end - n, n)])
            offsets.append(np.append(0, end))
        return Bags(self.groups, ids, offsets)


#: Cells of a matrix of counts that is in memory at once.
COUNT_CELLS = 1 << 22


def _sums(net: Network, g: int, ids: np.ndarray, off: np.ndarray) -> np.ndarray:
    """Summed embeddings of each bag: full bags by a product of counts, others by gathering rows."""
    n, vocab = len(off) - 1, net.template.groups[g].vocab
    if not n:
        return np.zeros((0, net.template.groups[g].dim), np.float32)
    if len(ids) * 16 < n * vocab:
        return np.add.reduceat(net.rows(g, ids), off[:-1], axis=0)
    out, step = [], max(1, COUNT_CELLS // vocab)
    for a in range(0, n, step):
        b = min(a + step, n)
        part = ids[off[a] : off[b]] + np.repeat(np.arange(b - a), np.diff(off[a : b + 1])) * vocab
        out.append(net.product(g, np.bincount(part, minlength=(b - a) * vocab).reshape(b - a, vocab).astype(np.float32)))
    return np.concatenate(out)


def embed(net: Network, x: Bags, combine: str = "mean") -> np.ndarray:
    out = []
    for g, ids, off in zip(x.groups, x.ids, x.offsets, strict=True):
        total = _sums(net, g, ids, off)
        out.append(total / np.diff(off)[:, None].astype(total.dtype) if combine == "mean" else total)
    return np.concatenate(out, axis=1)


def predict(net: Network, x: Bags, combine: str = "mean", block: int = 4096) -> np.ndarray:
    rows = [net.logits(embed(net, x.take(np.arange(a, min(a + block, len(x)))), combine)) for a in range(0, len(x), block)]
    return np.concatenate(rows) if rows else np.zeros((0, len(net.classes)), np.float32)


def loss_and_grad(net: Network, x: Bags, y: np.ndarray, l2: float = 0.0, combine: str = "mean") -> tuple[float, list[np.ndarray]]:
    """Mean cross-entropy plus ``l2`` times the squares of hidden weights and biases, and its gradients."""
    h0 = embed(net, x, combine)
    a = h0 @ net.w.T + net.c
    h1 = np.maximum(a, 0)
    z = h1 @ net.beta.T + net.b
    z = z - z.max(1, keepdims=True)
    p = np.exp(z)
    p /= p.sum(1, keepdims=True)
    n = len(y)
    loss = float(-np.log(np.maximum(p[np.arange(n), y], 1e-12)).mean() + l2 * ((net.w**2).sum() + (net.c**2).sum() + (net.b**2).sum()))
    p[np.arange(n), y] -= 1
    dz = p / n
    da = (dz @ net.beta) * (a > 0)
    dh0 = da @ net.w
    grads = [np.zeros_like(e) for e in net.embeddings]
    at = 0
    for g, ids, off in zip(x.groups, x.ids, x.offsets, strict=True):
        d = net.embeddings[g].shape[1]
        part, many = dh0[:, at : at + d], np.diff(off)
        if combine == "mean":
            part = part / many[:, None]
        cells = (ids[:, None] * d + np.arange(d)).ravel()  # NumPy adds at places of one dimension and one type much faster
        np.add.at(grads[g].reshape(-1), cells, np.repeat(part.astype(grads[g].dtype), many, axis=0).ravel())
        at += d
    return loss, [*grads, da.T @ h0 + 2 * l2 * net.w, da.sum(0) + 2 * l2 * net.c, dz.T @ h1, dz.sum(0) + 2 * l2 * net.b]


@dataclass(frozen=True)
class Settings:
    lr: float = 0.2
    momentum: float = 0.9
    decay: float = 0.96
    decay_steps: int = 200
    l2: float = 1e-5
    batch: int = 32
    epochs: int = 4
    patience: int = 3
    average: bool = True
    combine: str = "mean"
    seed: int = 1


def rate(s: Settings, step: int) -> float:
    return s.lr * s.decay ** (step / s.decay_steps)


def sgd(net: Network, x: Bags, y: np.ndarray, s: Settings, dev: tuple[Bags, np.ndarray] | None = None, every: int = 200, metric: Callable | None = None) -> tuple[Network, list[float]]:
    """Trains a copy; returns the averaged parameters of the best held-out measure, and the measures."""
    net, rng = net.copy(), np.random.default_rng(s.seed)
    params = net.parameters()
    speed, mean = [np.zeros_like(p) for p in params], net.copy()
    averaged, count, step, history, best, worse = mean.parameters(), 0, 0, [], (-1.0, net.copy()), 0
    start = max(1, len(y) // s.batch)  # averaging starts after the first pass
    judge = metric or (lambda n, d: float((predict(n, d[0], s.combine).argmax(1) == d[1]).mean()))
    for _ in range(s.epochs):
        for rows in np.array_split(rng.permutation(len(y)), max(1, len(y) // s.batch)):
            _, grads = loss_and_grad(net, x.take(rows), y[rows], s.l2, s.combine)
            lr = rate(s, step)
            for p, v, g in zip(params, speed, grads, strict=True):
                v *= s.momentum
                v -= lr * g
                p += v
            step += 1
            if not s.average:
                pass  # the mean is taken where it is read
            elif step <= start:
                for m, p in zip(averaged, params, strict=True):
                    m[...] = p
            else:
                count += 1
                for m, p in zip(averaged, params, strict=True):
                    m += (p - m) / count
            if dev is not None and step % every == 0:
                if not s.average:
                    mean = net.copy()
                history.append(judge(mean, dev))
                if history[-1] > best[0]:
                    best, worse = (history[-1], mean.copy()), 0
                else:
                    worse += 1
                if worse >= s.patience:
                    return best[1], history
    if not s.average:
        mean = net
    if dev is not None:
        history.append(judge(mean, dev))
        return (mean if history[-1] >= best[0] else best[1]), history
    return mean, history


GRID = [{"lr": lr, "momentum": m, "l2": l2, "decay": d} for lr in (0.05, 0.2) for m in (0.8, 0.9) for l2 in (0.0, 1e-4) for d in (0.9, 0.96)]


def grid(spark: SparkSession, start: Network, x: Bags, y: np.ndarray, dev: tuple[Bags, np.ndarray], settings: Settings, trials: list[dict] = GRID, metric: Callable | None = None) -> DataFrame:
    """(trial, params, metric): one Spark task per trial over a broadcast sample (its size is bounded by the caller).

    ``metric``: the task's measure of (network, dev), by which training also stops early; decision accuracy if none is given.
    """
    held = spark.sparkContext.broadcast((start, x, y, dev))

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            for t in batch["trial"]:
                net, x, y, dev = held.value
                _, history = sgd(net, x, y, replace(settings, **trials[t]), dev, metric=metric)
                yield pd.DataFrame({"trial": [t], "params": [str(trials[t])], "metric": [max(history)]})

    return spark.range(len(trials)).withColumnRenamed("id", "trial").repartition(len(trials)).mapInPandas(run, "trial long, params string, metric double")


def sql_step(features: DataFrame, labels: DataFrame, weights: DataFrame, key: str, label: str, lr: float) -> DataFrame:
    """One full-batch gradient step of a softmax layer without a hidden one, in relational form.

    features (key, v, x), labels (key, label), weights (class, v, w: few rows) -> (class, v, grad, w), the gradient of the mean cross-entropy.
    """
    few = F.broadcast(weights)
    z = features.join(few, "v").groupBy(key, "class").agg(F.sum(F.col("x") * F.col("w")).alias("z"))
    row = Window.partitionBy(key)
    e = z.withColumn("e", F.exp(F.col("z") - F.max("z").over(row)))
    p = e.withColumn("p", F.col("e") / F.sum("e").over(row)).join(labels.select(key, F.col(label).alias("gold")), key)
    delta = p.select(key, "class", (F.col("p") - (F.col("class") == F.col("gold")).cast("double")).alias("d"))
    n = labels.agg(F.count(F.lit(1)).alias("n"))
    grad = features.join(delta, key).groupBy("class", "v").agg(F.sum(F.col("x") * F.col("d")).alias("g"))
    done = few.join(grad, ["class", "v"], "left").crossJoin(F.broadcast(n))  # a single row
    g = F.coalesce("g", F.lit(0.0)) / F.col("n")
    return done.select("class", "v", g.alias("grad"), (F.col("w") - lr * g).alias("w"))


def local_sgd(rows: DataFrame, start: Network, featurize: Callable[[pd.DataFrame], tuple[Bags, np.ndarray]], settings: Settings, rounds: int = 2) -> Network:
    """Data-parallel training: every partition takes SGD steps over its rows, parameters are averaged by row counts each round."""
    net = start.copy()
    for _ in range(rounds):
        held = rows.sparkSession.sparkContext.broadcast(net)

        def run(batches: Iterator[pd.DataFrame], held=held) -> Iterator[pd.DataFrame]:
            mine, n = held.value, 0
            for batch in batches:
                x, y = featurize(batch)
                if len(y):
                    mine, _ = sgd(mine, x, y, replace(settings, epochs=1))
                    n += len(y)
            if n:
                for i, p in enumerate(mine.parameters()):
                    yield pd.DataFrame({"i": [i], "n": [n], "value": [(p.ravel() * n).astype(np.float64).tolist()]})

        # Sums element by element inside Spark: one row per parameter matrix reaches the driver.
        parts = rows.mapInPandas(run, "i int, n long, value array<double>")
        summed = parts.select("i", "n", F.posexplode("value").alias("at", "x")).groupBy("i", "at").agg((F.sum("x") / F.sum("n")).alias("x"))
        got = summed.groupBy("i").agg(F.transform(F.array_sort(F.collect_list(F.struct("at", "x"))), lambda s: s["x"]).alias("value")).collect()
        params = net.parameters()
        for r in got:
            params[r["i"]][...] = np.array(r["value"], np.float32).reshape(params[r["i"]].shape)
    return net
