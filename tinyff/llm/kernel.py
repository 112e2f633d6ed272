"""Vectorised text kernels over Arrow buffers.

Texts stay UTF-8 bytes. Words are maximal runs of word bytes inside one text;
they are hashed to 64 bits by a polynomial over per-byte random values, for all
words of a block at once. ASCII capitals may be folded by the byte table itself.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa

BLOCK_BYTES = 1 << 18
_BASE = np.uint64(0x9E3779B97F4A7C15 | 1)
_INVERSE = np.uint64(pow(int(_BASE), -1, 1 << 64))
_POWERS: dict[str, np.ndarray] = {}


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    if not _POWERS or len(_POWERS["up"]) < n:
        size = max(n, 2 * BLOCK_BYTES)
        for name, base in (("up", _BASE), ("down", _INVERSE)):
            p = np.full(size, base, np.uint64)
            p[0] = 1
            _POWERS[name] = np.multiply.accumulate(p)
    return _POWERS["up"], _POWERS["down"]


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective finaliser on 64-bit values."""
    x = x ^ (x >> np.uint64(32))
    x = x * np.uint64(0xD6E8FEB86659FD93)
    x = x ^ (x >> np.uint64(29))
    x = x * np.uint64(0xA3B195354A39B70D)
    return x ^ (x >> np.uint64(32))


class Alphabet:
    """Which bytes belong to words, and each byte's random value (capitals as small letters if ``fold``)."""

    def __init__(self, word: Callable[[int], bool], fold: bool = True):
        self.word = np.array([word(b) for b in range(256)])
        code = np.arange(256, dtype=np.uint64)
        if fold:
            code[65:91] += np.uint64(32)
        self.value = mix(code + np.uint64(0x5851F42D4C957F2D))


#: Runs of anything but blanks (space and \t to \r).
BLANK_SPLIT = Alphabet(lambda b: b != 0x20 and not 0x09 <= b <= 0x0D)
#: Runs of ASCII letters, digits and all non-ASCII characters.
ALNUM = Alphabet(lambda b: 0x30 <= b <= 0x39 or 0x41 <= b <= 0x5A or 0x61 <= b <= 0x7A or b >= 0x80)


class Words:
    """All words of one block: ``hash``, byte ``start`` and ``end``, and for text i the range ``bounds[i]:bounds[i+1]``."""

    __slots__ = ("bounds", "end", "hash", "start")

    def __init__(self, data: np.ndarray, offsets: np.ndarray, alphabet: Alphabet):
        n = len(data)
        inside = alphabet.word[data]
        first = np.zeros(n + 1, bool)
        first[offsets] = True
        before = np.empty(n, bool)
        after = np.empty(n, bool)
        if n:
            before[0] = after[-1] = False
            before[1:], after[:-1] = inside[:-1], inside[1:]
        self.start = np.flatnonzero(inside & (~before | first[:-1]))
        self.end = np.flatnonzero(inside & (~after | first[1:])) + 1
        up, down = _powers(n + 1)
        total = np.zeros(n + 1, np.uint64)
        np.cumsum(alphabet.value[data] * up[:n], out=total[1:])
        self.hash = mix((total[self.end] - total[self.start]) * down[self.start] + (self.end - self.start).astype(np.uint64))
        self.bounds = np.searchsorted(self.start, offsets)


_FACTORS = mix(np.arange(1, 257, dtype=np.uint64)) | np.uint64(1)


def shingles(words: Words, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of k consecutive words at every word position, and where they fit inside their text."""
    h, n = words.hash, len(words.hash)
    out = np.zeros(n, np.uint64)
    for j in range(min(k, n)):
        out[: n - j] += h[j:] * _FACTORS[j]
    last = np.repeat(words.bounds[1:], np.diff(words.bounds))
    return mix(out + np.uint64(k)), np.arange(n) + k <= last


def sequence_hash(h: np.ndarray) -> np.uint64:
    """The hash that ``shingles`` gives to exactly these words."""
    return mix(np.add.reduce(h * _FACTORS[: len(h)], keepdims=True) + np.uint64(len(h)))[0]


def blocks(batches: Iterator[pa.RecordBatch], text: str = "text", most: int = BLOCK_BYTES) -> Iterator[tuple[pa.RecordBatch, np.ndarray, np.ndarray]]:
    """Row slices of about ``most`` bytes of text with their byte buffer and offsets; null texts are empty."""
    for batch in batches:
        column = batch.column(batch.schema.get_field_index(text))
        if column.null_count:
            column = column.fill_null("")
        if not pa.types.is_large_string(column.type):
            column = column.cast(pa.large_string())
        if not len(column):
            continue
        raw = column.buffers()
        offsets = np.frombuffer(raw[1], np.int64)[column.offset : column.offset + len(column) + 1]
        data = np.frombuffer(raw[2], np.uint8) if raw[2] is not None else np.zeros(0, np.uint8)
        at = 0
        while at < len(column):
            to = max(at + 1, int(np.searchsorted(offsets, offsets[at] + most, "right")) - 1)
            yield batch.slice(at, to - at), data[offsets[at] : offsets[to]], offsets[at : to + 1] - offsets[at]
            at = to


def find(table: np.ndarray, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Positions of ``keys`` in a sorted table, and which of them are there."""
    if not len(table):
        return np.zeros(len(keys), np.int64), np.zeros(len(keys), bool)
    at = np.searchsorted(table, keys)
    at[at == len(table)] = 0
    return at, table[at] == keys


class Lookup:
    """A sorted table of 64-bit keys with a directory over the top bits, for many fast look-ups."""

    def __init__(self, keys: np.ndarray):
        self.keys = keys
        self.bits = max(1, min(20, int(np.ceil(np.log2(len(keys) + 1)))))
        slots = np.arange((1 << self.bits) + 1, dtype=np.uint64)
        top = keys >> np.uint64(64 - self.bits)
        self.first = np.searchsorted(top, slots).astype(np.int64)
        self.depth = int(np.diff(self.first).max()) if len(keys) else 0

    def find(self, wanted: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        if not len(self.keys):
            return np.zeros(len(wanted), np.int64), np.zeros(len(wanted), bool)
        slot = (wanted >> np.uint64(64 - self.bits)).astype(np.int64)
        at, stop = self.first[slot], self.first[slot + 1]
        for _ in range(self.depth):
            on = at < stop
            move = on & (self.keys[np.minimum(at, len(self.keys) - 1)] < wanted)
            if not move.any():
                break
            at = at + move
        at = np.minimum(at, len(self.keys) - 1)
        return at, self.keys[at] == wanted
