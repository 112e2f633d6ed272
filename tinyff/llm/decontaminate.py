"""Benchmark decontamination by a prefix-filtered join of word windows.

Every benchmark item gives windows of ``window`` consecutive words (a shorter item
is one window). A window's tokens are its shingles of up to ``SHINGLE`` words,
ordered by rarity in the corpus; as a text must contain the whole window, one
token, the rarest, is a sufficient prefix. Documents are probed for prefix tokens
only; a hit fixes where the window would have to start, length and position bounds
drop starts outside the text, and the full sequence of word identities decides.

The benchmark is a stated query set: it is processed in blocks of at most
``block_windows`` windows, each block broadcast (a bounded size), and hits of
several blocks are merged by the digest of the text and joined to all rows.

Defined cases: null and empty texts have no words and are never contaminated;
items without words have no window; every row is reported, whatever its id;
repeated item ids are listed once; items without an id hit words like others and
are listed as one null, which the digest leaves out; further columns are ignored
or kept by name; empty tables give no hits.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..plans.scratch import materialise, small_side
from .kernel import ALNUM, Lookup, Words, blocks, mix, shingles
from .rows import with_text_columns

WINDOW = 13
SHINGLE = 3
BLOCK_WINDOWS = 500_000


class WindowIndex:
    """The windows of one block of items: word identities, owners, and the probing table of prefix tokens."""

    def __init__(self, ids: list[str], words: list[np.ndarray], window: int):
        owner, rows = [], []
        for i, w in enumerate(words):
            k = min(window, len(w))
            for s in range(len(w) - k + 1 if k else 0):
                owner.append(i)
                rows.append(w[s : s + k])
        self.ids, self.owner = np.array(ids, object), np.array(owner, np.int64)
        self.length = np.array([len(r) for r in rows], np.int64)
        self.words = np.zeros((len(rows), window), np.uint64)
        for i, r in enumerate(rows):
            self.words[i, : len(r)] = r
        # One text per window, so that shingles of the kernel can be taken of all windows at once.
        flat = np.concatenate(rows) if rows else np.zeros(0, np.uint64)
        self.bounds = np.append(0, np.cumsum(self.length)) if rows else np.zeros(1, np.int64)
        self.tokens = {k: _rolled(flat, self.bounds, k) for k in range(1, SHINGLE + 1)}
        self.size = np.minimum(self.length, SHINGLE)

    def shingle_keys(self) -> np.ndarray:
        return np.unique(np.concatenate([t[ok] for t, ok in self.tokens.values()])) if len(self.length) else np.zeros(0, np.uint64)

    def choose_prefixes(self, keys: np.ndarray, frequency: np.ndarray) -> None:
        """Sorted prefix tokens, and for each the windows that it stands for with its place in them."""
        key, at, place = [], [], []
        for i in range(len(self.length)):
            a, b = self.bounds[i], self.bounds[i + 1] - self.size[i] + 1
            tokens = self.tokens[int(self.size[i])][0][a:b]
            rarity = frequency[np.searchsorted(keys, tokens)]
            j = int(np.lexsort((tokens, rarity))[0])
            key.append(tokens[j])
            at.append(i)
            place.append(j)
        order = np.argsort(np.array(key, np.uint64), kind="stable") if key else np.zeros(0, np.int64)
        key, self.at, self.place = (np.array(x)[order] for x in (np.array(key, np.uint64), np.array(at, np.int64), np.array(place, np.int64)))
        self.prefix, first = np.unique(key, return_index=True)
        self.first = np.append(first, len(key)).astype(np.int64)
        self.sizes = np.unique(self.size)


def _rolled(h: np.ndarray, bounds: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    words = Words.__new__(Words)
    words.hash, words.bounds = h, bounds
    token, fits = shingles(words, k)
    return mix(token ^ np.uint64(k)), fits


def item_words(text: str | None) -> np.ndarray:
    raw = np.frombuffer((text or "").encode(), np.uint8)
    return Words(raw, np.array([0, len(raw)]), ALNUM).hash


def shingle_frequency(docs: DataFrame, text_col: str, keys: np.ndarray) -> np.ndarray:
    """Occurrences of each benchmark shingle in all documents: the order of rarity."""
    held = docs.sparkSession.sparkContext.broadcast(keys)

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table, seen = Lookup(held.value), np.zeros(len(held.value), np.int64)
        for _, data, offsets in blocks(batches, text_col):
            words = Words(data, offsets, ALNUM)
            for k in range(1, SHINGLE + 1):
                token, fits = _rolled(words.hash, words.bounds, k)
                at, known = table.find(token[fits])
                seen += np.bincount(at[known], minlength=len(seen))
        some = np.flatnonzero(seen)
        yield pa.record_batch({"at": pa.array(some.astype(np.int32)), "n": pa.array(seen[some])})

    got = docs.select(text_col).mapInArrow(count, "at int, n long").groupBy("at").agg(F.sum("n").alias("n")).toArrow()
    out = np.zeros(len(keys), np.int64)
    out[got.column("at").to_numpy()] = got.column("n").to_numpy()
    return out


def occurrences(words: Words, index: WindowIndex) -> tuple[np.ndarray, np.ndarray]:
    """(window, first word) of every occurrence inside its text."""
    n = len(words.hash)
    last = np.repeat(words.bounds[1:], np.diff(words.bounds))
    begin = np.repeat(words.bounds[:-1], np.diff(words.bounds))
    table, windows, starts = Lookup(index.prefix), [], []
    for k in index.sizes:
        token, fits = _rolled(words.hash, words.bounds, int(k))
        here = np.flatnonzero(fits)
        at, known = table.find(token[here])
        here, at = here[known], at[known]
        many = index.first[at + 1] - index.first[at]
        slot = np.repeat(index.first[at], many) + np.arange(many.sum()) - np.repeat(np.cumsum(many) - many, many)
        window = index.at[slot]
        where = np.repeat(here, many)
        start = where - index.place[slot]
        ok = (index.size[window] == k) & (start >= begin[where]) & (start + index.length[window] <= last[where])
        window, start = window[ok], start[ok]
        for j in range(index.words.shape[1]):  # verification, word by word over all candidates that are left
            inside = j < index.length[window]
            same = ~inside | (index.words[window, j] == words.hash[np.minimum(start + j, n - 1)])
            window, start = window[same], start[same]
        windows.append(window)
        starts.append(start)
    return (np.concatenate(windows), np.concatenate(starts)) if windows else (np.zeros(0, np.int64), np.zeros(0, np.int64))


def _hits(index_of):
    """A block function: words of each text, its hit word ranges (as pairs) and the items that occur."""

    def make():
        index = index_of()

        def run(data: np.ndarray, offsets: np.ndarray) -> dict:
            words = Words(data, offsets, ALNUM)
            n = len(offsets) - 1
            window, start = occurrences(words, index) if len(words.hash) and len(index.prefix) else (np.zeros(0, np.int64),) * 2
            owner = np.searchsorted(words.bounds, start, "right") - 1
            cover = np.zeros(len(words.hash) + 1, np.int64)
            np.add.at(cover, start, 1)
            np.add.at(cover, start + index.length[window], -1)
            hit = np.append(0, np.cumsum(np.cumsum(cover[:-1]) > 0))
            ranges, items = [[] for _ in range(n)], [set() for _ in range(n)]
            for o in np.unique(owner):
                mine = owner == o
                items[o] = set(index.ids[index.owner[window[mine]]].tolist())
                base = words.bounds[o]
                pairs = np.unique(np.column_stack([start[mine] - base, start[mine] - base + index.length[window[mine]]]), axis=0)
                ranges[o] = pairs.ravel().tolist()
            return {
                "n_words": np.diff(words.bounds).astype(np.int64),
                "n_hit": (hit[words.bounds[1:]] - hit[words.bounds[:-1]]).astype(np.int64),
                "hit_ranges": pa.array(ranges, pa.list_(pa.int64())),
                "items": pa.array([sorted(s, key=lambda x: (x is None, x)) for s in items], pa.list_(pa.string())),
            }

        return run

    return make


def build_indexes(docs: DataFrame, benchmark: DataFrame, text_col: str, item_col: str, item_text_col: str, window: int, block_windows: int) -> Iterator[WindowIndex]:
    """Indexes over successive blocks of items; the items stream through the driver, one block at a time."""
    ids, words, size = [], [], 0

    def made() -> WindowIndex:
        index = WindowIndex(ids, words, window)
        keys = index.shingle_keys()
        index.choose_prefixes(keys, shingle_frequency(docs, text_col, keys))
        return index

    rows = benchmark.select(F.col(item_col).cast("string").alias("item"), F.col(item_text_col).alias("text"))
    for r in rows.toLocalIterator():
        w = item_words(r["text"])
        if len(w):
            ids.append(r["item"])
            words.append(w)
            size += max(1, len(w) - window + 1)
        if size >= block_windows:
            yield made()
            ids, words, size = [], [], 0
    if ids:
        yield made()


def _covered(ranges: Column) -> Column:
    """Words covered by a flat list of (from, to) pairs, by a sweep."""
    pairs = F.array_sort(F.transform(F.sequence(F.lit(0), (F.size(ranges) / 2 - 1).cast("int")), lambda i: F.struct(F.get(ranges, (2 * i).cast("int")).alias("a"), F.get(ranges, (2 * i + 1).cast("int")).alias("b"))))
    zero = F.struct(F.lit(0).cast("long").alias("n"), F.lit(0).cast("long").alias("to"))
    step = lambda s, p: F.struct((s["n"] + F.greatest(p["b"] - F.greatest(p["a"], s["to"]), F.lit(0))).alias("n"), F.greatest(s["to"], p["b"]).alias("to"))
    return F.aggregate(pairs, zero, step, lambda s: s["n"])


def _merged(docs: DataFrame, parts: list[DataFrame], text_col: str, keep: list[str]) -> DataFrame:
    """The hits of several blocks, brought to every row through the digest of its text: what occurs depends on the text alone.

    Only texts with hits are grouped, each block giving a text once.
    """
    every = parts[0]
    for p in parts[1:]:
        every = every.unionByName(p)
    grouped = every.groupBy("_digest").agg(F.flatten(F.collect_list("hit_ranges")).alias("_ranges"), F.array_sort(F.array_distinct(F.flatten(F.collect_list("items")))).alias("items"))
    hits = small_side(materialise(grouped.select("_digest", _covered(F.col("_ranges")).alias("n_hit"), "items"), "hits"))

    def words_only():
        return lambda data, offsets: {"n_words": np.diff(Words(data, offsets, ALNUM).bounds).astype(np.int64)}

    rows = with_text_columns(docs.withColumn("_digest", _digest(text_col)), text_col, words_only, {"n_words": T.LongType()}, [c for c in keep if c not in ("n_hit", "items")] + ["_digest"])
    joined = rows.join(hits, "_digest", "left")
    none = F.array().cast("array<string>")
    return joined.select(*[c for c in rows.columns if c != "_digest"], F.coalesce("n_hit", F.lit(0).cast("long")).alias("n_hit"), F.coalesce("items", none).alias("items"))


def _digest(text_col: str) -> Column:
    return F.unhex(F.sha2(F.coalesce(F.col(text_col), F.lit("")), 256))


def contamination(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text", window: int = WINDOW, block_windows: int = BLOCK_WINDOWS, keep: list[str] | None = None) -> DataFrame:
    """One row per input row: ``keep`` (default: the id) with ``n_words``, ``n_hit``, ``items`` (sorted) and ``contaminated``: at least a twentieth of the words hit.

    Rows and columns are the same for any ``block_windows``. A kept column of a new one's name is replaced.
    """
    sc, keep = docs.sparkSession.sparkContext, [id_col] if keep is None else keep
    new = {"n_words": T.LongType(), "n_hit": T.LongType(), "hit_ranges": T.ArrayType(T.LongType()), "items": T.ArrayType(T.StringType())}
    held, parts = None, []

    def part() -> DataFrame:
        hits = with_text_columns(docs.select(text_col, _digest(text_col).alias("_digest")), text_col, _hits(lambda held=held: held.value), new, ["_digest"])
        return materialise(hits.where(F.size("items") > 0).select("_digest", "hit_ranges", "items").dropDuplicates(["_digest"]), "block-hits")

    for index in build_indexes(docs, benchmark, text_col, item_col, item_text_col, window, block_windows):
        if held is not None:
            parts.append(part())
        held = sc.broadcast(index)
    if parts:
        found = _merged(docs, [*parts, part()], text_col, keep)
    elif held is None:
        empty = WindowIndex([], [], window)
        empty.choose_prefixes(np.zeros(0, np.uint64), np.zeros(0, np.int64))
        found = with_text_columns(docs, text_col, _hits(lambda: empty), new, keep).drop("hit_ranges")
    else:
        found = with_text_columns(docs, text_col, _hits(lambda held=held: held.value), new, keep).drop("hit_ranges")
    return found.withColumn("contaminated", (F.col("n_hit") > 0) & (20 * F.col("n_hit") >= F.col("n_words")))


def item_digest(items: Column) -> Column:
    """SHA-256 of the comma-joined, string-sorted item ids."""
    return F.sha2(F.array_join(F.array_sort(items), ","), 256)

