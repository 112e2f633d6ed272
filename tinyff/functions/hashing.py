"""Random feature mixing: n-grams to a fixed number of buckets, without a dictionary."""

from __future__ import annotations

import hashlib

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def bucket(value: Column, size: int, algo: str = "xxhash64", seed: int = 0) -> Column:
    """Bucket 0 .. size - 1 of a string."""
    if algo == "xxhash64":
        h = F.xxhash64(value, F.lit(seed)) if seed else F.xxhash64(value)
    elif algo == "md5":
        h = F.conv(F.substring(F.md5(F.concat(F.lit(str(seed)), value) if seed else value), 1, 8), 16, 10).cast("long")
    elif algo == "crc32":
        h = F.crc32(value.cast("binary"))
    else:
        raise ValueError(f"no hash is named {algo}")
    return F.pmod(h, F.lit(size)).cast("int")


def audit(grams: DataFrame, column: str, size: int, algo: str = "md5") -> DataFrame:
    """Load and collisions of the distinct values of ``column`` over ``size`` buckets, with the chi-square of an even spread."""
    loads = grams.select(column).distinct().groupBy(bucket(F.col(column), size, algo).alias("v")).agg(F.count(F.lit(1)).alias("n"))
    even = F.sum("n") / size
    return loads.agg(
        F.lit(size).cast("long").alias("buckets"), F.sum("n").alias("values"), F.count(F.lit(1)).alias("used"), F.max("n").alias("fullest"),
        (F.sum("n") - F.count(F.lit(1))).alias("collisions"), F.round(F.sum(F.col("n") * F.col("n")) / even - F.sum("n"), 6).alias("chi_square"),
    )


_MIX = np.uint64(0x9E3779B97F4A7C15)


def _settle(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(31))) * np.uint64(0xD6E8FEB86659FD93)
    return h ^ (h >> np.uint64(32))


class Block:
    """The code points of many texts side by side, with each place's distance to the end of its text."""

    def __init__(self, texts: list[str]):
        self.size = np.fromiter(map(len, texts), np.int64, len(texts))
        self.text = "".join(texts)
        self.code = np.frombuffer(self.text.encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64) + np.uint64(1)
        self.room = np.repeat(np.cumsum(self.size), self.size) - np.arange(len(self.code))

    def grams(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        """64-bit identities of all n-grams inside texts (a polynomial), and their places."""
        at = np.flatnonzero(self.room >= n)
        h = np.zeros(len(at), np.uint64)
        for k in range(n):
            h = h * _MIX + self.code[at + k]
        return _settle(h), at

    def counts(self, n: int) -> np.ndarray:
        """N-grams of each text."""
        return np.maximum(self.size - n + 1, 0)


def gram_bags(texts: list[str], n: int, size: int) -> tuple[np.ndarray, np.ndarray]:
    """Buckets of the n-grams of many texts, and the offsets of each text's bag; a bag without n-grams is the bucket 0."""
    block = Block(texts)
    many = block.counts(n)
    room = np.maximum(many, 1)
    ids = np.zeros(int(room.sum()), np.int64)
    ids[np.repeat(many > 0, room)] = (block.grams(n)[0] % np.uint64(size)).astype(np.int64)
    return ids, np.append(0, np.cumsum(room))


def gram_buckets(text: str, n: int, size: int) -> np.ndarray:
    """A bucket for each character n-gram of one text, by the same polynomial."""
    return (Block([text]).grams(n)[0] % np.uint64(size)).astype(np.int32)


class Md5Buckets:
    """md5 buckets of the n-grams of a block of texts; each distinct n-gram is hashed about once in a worker.

    N-grams are known by 64-bit identities in a table of ``ROOM`` places; one that lost its place is hashed again.
    """

    ROOM_BITS = 20

    def __init__(self, n: int, size: int):
        self.n, self.size = n, size
        places = np.arange(1 << self.ROOM_BITS, dtype=np.uint64)
        self.keys = (places ^ np.uint64(1)) << np.uint64(64 - self.ROOM_BITS)  # a key that belongs elsewhere: an empty place
        self.values = np.zeros(1 << self.ROOM_BITS, np.int64)

    def __call__(self, block: Block) -> np.ndarray:
        key, at = block.grams(self.n)
        place = (key >> np.uint64(64 - self.ROOM_BITS)).astype(np.int64)
        out = self.values[place]
        miss = np.flatnonzero(self.keys[place] != key)
        if len(miss):
            fresh, first, back = np.unique(key[miss], return_index=True, return_inverse=True)
            made = np.fromiter((int(hashlib.md5(block.text[i : i + self.n].encode()).hexdigest()[:8], 16) % self.size for i in at[miss[first]].tolist()), np.int64, len(fresh))
            out[miss] = made[back]
            mine = (fresh >> np.uint64(64 - self.ROOM_BITS)).astype(np.int64)
            self.keys[mine], self.values[mine] = fresh, made
        return out
