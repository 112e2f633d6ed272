"""Bloom maps: approximate key to value maps in a bit set.

Variant ``pairs``: a (key, value) pair sets k positions; a look-up probes the
values from the most frequent on and returns the first whose positions are all
set. Variant ``tree``: values are leaves of a Huffman tree; a key sets positions
for every node on the way to its value, and a look-up follows all ways that are
set and returns the first leaf. A stored key always has its own value among the
hits, though another may come first.

Keys are hashed once; all positions come from that hash and whole numbers, by the
same 64-bit function in Spark and NumPy, so a map is built where the words are and
looked up for many words at a time.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

SEGMENT = 64
#: Values of a map, and bytes of its bit set, that a driver takes.
MOST_VALUES, MOST_BYTES = 4096, 1 << 28
_P1, _P2, _P3, _P4, _P5 = (np.uint64(x) for x in (0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5))


def key_hash(words: list[str]) -> np.ndarray:
    """What Spark's ``xxhash64`` gives for each word."""
    return np.fromiter((xxhash.xxh64_intdigest(w.encode("utf-8", "surrogatepass"), 42) for w in words), np.uint64, len(words))


def _turn(x: np.ndarray, by: int) -> np.ndarray:
    return (x << np.uint64(by)) | (x >> np.uint64(64 - by))


def _number_hash(x: np.ndarray, seed: np.ndarray) -> np.ndarray:
    """``xxhash64`` of whole 64-bit numbers under a seed each."""
    h = (seed + _P5 + np.uint64(8)) ^ (_turn(x * _P2, 31) * _P1)
    h = _turn(h, 27) * _P1 + _P4
    h = (h ^ (h >> np.uint64(33))) * _P2
    h = (h ^ (h >> np.uint64(29))) * _P3
    return h ^ (h >> np.uint64(32))


def positions(keys: np.ndarray, item: int | np.ndarray, i: int, size: int) -> np.ndarray:
    """The i-th position of (key, item) pairs."""
    item = np.broadcast_to(np.asarray(item, np.int64).view(np.uint64), keys.shape)
    h = _number_hash(np.array([i], np.uint64), _number_hash(item, _number_hash(keys, np.array([42], np.uint64))))
    return np.mod(h.view(np.int64), size)


def position(key: Column, item: Column, i: Column, size: int) -> Column:
    """The same in Spark; ``key`` is the key's ``xxhash64``."""
    return F.pmod(F.xxhash64(key, item.cast("long"), i.cast("long")), F.lit(size))


def huffman(frequency: dict[int, int]) -> dict[int, str]:
    """A prefix code; a single value has the empty code."""
    heap = [(n, v, {v: ""}) for v, n in frequency.items()]
    heapq.heapify(heap)
    while len(heap) > 1:
        a, b = heapq.heappop(heap), heapq.heappop(heap)
        heapq.heappush(heap, (a[0] + b[0], min(a[1], b[1]), {v: "0" + c for v, c in a[2].items()} | {v: "1" + c for v, c in b[2].items()}))
    return heap[0][2] if heap else {}


def entropy(frequency: dict[int, int]) -> float:
    n = np.array(list(frequency.values()), float)
    p = n / n.sum()
    return float(-(p * np.log2(p)).sum())


def _node(code: str) -> int:
    """A node of the tree as a number: its code behind a leading one."""
    return int("1" + code, 2)


@dataclass
class BloomMap:
    bits: np.ndarray
    size: int
    hashes: dict[int, int]
    values: list[int]
    codes: dict[int, str]
    variant: str
    nodes: set = field(init=False)
    leaves: dict = field(init=False)

    def __post_init__(self):
        self.leaves = {_node(c): v for v, c in self.codes.items()}
        self.nodes = {_node(c[:i]) for c in self.codes.values() for i in range(len(c) + 1)}

    def _has(self, keys: np.ndarray, item: int | np.ndarray, k: int) -> np.ndarray:
        """Whether all k positions of (key, item) are set."""
        on = np.arange(len(keys))
        item = np.broadcast_to(np.asarray(item, np.int64), keys.shape)
        for i in range(k):
            p = positions(keys[on], item[on], i, self.size)
            on = on[(self.bits[p >> 6] >> (p & 63).astype(np.uint64) & np.uint64(1)) == 1]
        out = np.zeros(len(keys), bool)
        out[on] = True
        return out

    def find(self, keys: np.ndarray) -> np.ndarray:
        """The value of each key, given by its hash; -1 where there is none."""
        out = np.full(len(keys), -1, np.int64)
        if self.variant == "pairs":
            left = np.arange(len(keys))
            for v in self.values:
                hit = self._has(keys[left], v, self.hashes[v])
                out[left[hit]] = v
                left = left[~hit]
            return out
        if not self.leaves:
            return out
        who, node, best = np.arange(len(keys)), np.ones(len(keys), np.int64), {}
        one = len(self.leaves) == 1
        while len(who):
            if one or not (node == 1).all():  # the root of a tree with several leaves sets nothing
                hit = self._has(keys[who], node, self.hashes[-1])
                who, node = who[hit], node[hit]
            leaf = np.isin(node, list(self.leaves))
            for w, x in zip(who[leaf].tolist(), node[leaf].tolist(), strict=True):
                code = bin(x)[3:]
                if w not in best or code < best[w][0]:
                    best[w] = (code, self.leaves[x])
            who, node = np.repeat(who[~leaf], 2), (np.repeat(node[~leaf], 2) * 2) + np.tile([0, 1], int((~leaf).sum()))
            inside = np.isin(node, list(self.nodes))
            who, node = who[inside], node[inside]
        for w, (_, v) in best.items():
            out[w] = v
        return out

    def get(self, key: str) -> int | None:
        v = int(self.find(key_hash([key]))[0])
        return None if v < 0 else v

    @property
    def bytes(self) -> int:
        return self.size // 8


def build(df: DataFrame, key: str, value: str, bits_per_key: float = 10.0, variant: str = "pairs", priors: bool = False) -> BloomMap:
    """Positions are columns, segments of 64 bits are OR-ed in Spark; only the segments reach the driver, and their size is checked."""
    stats = {int(r[0]): int(r[1]) for r in df.groupBy(value).agg(F.count(F.lit(1))).limit(MOST_VALUES + 1).collect()}
    keys = max(1, sum(stats.values()))
    size = int(np.ceil(keys * bits_per_key / SEGMENT)) * SEGMENT
    if len(stats) > MOST_VALUES or size // 8 > MOST_BYTES:
        raise ValueError(f"a map of {len(stats)} values or {size // 8} bytes is too large")
    codes = huffman(stats)
    h = entropy(stats) if stats else 0.0
    order = sorted(stats, key=lambda v: (-stats[v], v))
    hashed, chosen = F.xxhash64(key), F.col(value).cast("int")
    if variant == "pairs":
        base = max(1, round(bits_per_key * np.log(2)))
        k = {v: max(1, base + (round(np.log2(stats[order[0]] / stats[v]) / 2) if priors else 0)) for v in order}
        items = F.array(chosen.cast("long"))
        many = F.element_at(F.create_map(*[F.lit(x) for kv in k.items() for x in kv]), chosen) if k else F.lit(0)
    else:
        k = {-1: max(1, round(bits_per_key / max(h, 1.0) * np.log(2)))}
        way = {v: [_node(c[:i]) for i in range(1, len(c) + 1)] or [1] for v, c in codes.items()}
        items = F.element_at(F.create_map(*[x for v, nodes in way.items() for x in (F.lit(v), F.array(*[F.lit(n).cast("long") for n in nodes]))]), chosen) if way else F.array().cast("array<long>")
        many = F.lit(k[-1])
    probes = df.select(hashed.alias("h"), F.explode(items).alias("item"), many.alias("k")).select("h", "item", F.explode(F.sequence(F.lit(0), F.col("k") - 1)).alias("i"))
    at = position(F.col("h"), F.col("item"), F.col("i"), size)
    segments = probes.select(at.alias("p")).groupBy(F.shiftright("p", 6).alias("segment")).agg(F.bit_or(F.expr("shiftleft(1L, cast(p & 63 as int))")).alias("word")).toPandas()
    bits = np.zeros(size // SEGMENT, np.uint64)
    bits[segments["segment"].to_numpy(np.int64)] = segments["word"].to_numpy().astype(np.int64).view(np.uint64)
    return BloomMap(bits, size, k, order, codes, variant)


def lookup(df: DataFrame, key: str, held: BloomMap, out: str = "found") -> DataFrame:
    """Adds the map's value of each key (null: none); the bit set is broadcast, hashes are made in Spark."""
    b = df.sparkSession.sparkContext.broadcast(held)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            found = b.value.find(batch["_hash"].to_numpy(np.int64).view(np.uint64))
            made = batch.drop(columns="_hash")
            made[out] = pd.array(found, "Int64")
            made.loc[found < 0, out] = pd.NA
            yield made

    schema = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in df.schema.fields) + f", {out} long"
    return df.withColumn("_hash", F.xxhash64(key)).mapInPandas(run, schema)
