"""N-gram Jaccard join as a blocked sparse matrix product.

Documents are rows and distinct word shingles columns of an incidence matrix; the
product of the matrix with its transpose holds all overlaps. Entries of the product
that cannot reach the similarity are not computed:

* columns are put in one global order, frequent ones last (a task's frequent
  columns are summed over tasks; any consistent order is right, a good one is fast);
* two documents that reach the similarity share a column among their first
  n - ceil(t n) + 1, and sizes, positions of the first shared column and parity bits
  bound the overlap: entries below these size-derived bounds are left out;
* rows are dealt into blocks. A cell is a pair of blocks with the entries wanted
  there; a row's columns are sent once to each cell that needs them. Inside a cell
  overlaps are accumulated over slices of columns, and after each slice the entries
  whose overlap so far and columns to come are below the bound are discarded.

Documents of equal sets are one class. Within a column, documents are first paired
with two leaders; columns of which the leaders met every pair, and columns whose
documents are already connected, need no more. In the others, rounds of hubs follow:
a column's hub is the document with the fewest rarer shingles, thus the nearest to
what its copies have in common, and further rounds have others. So large groups of
near copies cost a few entries per document. Whatever a column still holds
unconnected is then paired exactly, in blocks of its rows, so no component is ever
missed. The result is components; entries inside a component that is already known
are not all computed, so links are not counted. Joins by column deal the rows of
frequent columns over ``SALTS`` parts.

Defined cases: null, empty and blank texts have an empty set and link with nothing;
a text with fewer words than a shingle has its word sequence as one shingle;
repeated rows are reported each (all rows of one id carry one text); rows without
an id report their set and, as component, the smallest id of an equal set; further
columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..plans.scratch import materialise, small_side, spread
from .components import components
from .exact_dedup import group_digests
from .kernel import BLANK_SPLIT, Lookup, Words, blocks, mix, sequence_hash, shingles

#: Columns found this often inside one task's rows take part in the frequency order.
LOCAL_LEAST = 2
#: At most so many frequent columns, those above one frequency, are ordered by it (and broadcast).
MOST_FREQUENT = 1 << 20
#: Rows of a column of at least this frequency are salted over tasks.
HOT, SALTS = 1000, 64
#: 64-bit words of parity bits: a bit is set if an odd number of a set's shingles fall on it.
PARITY = 16
#: Rounds in which every column that is still open has a hub of its own.
ROUNDS = 1
#: Parity words (about 150 bytes a document) are broadcast for at most so many documents.
MARKS = 200_000
#: Shingles of the rows of a block (about; a cell has two blocks), the least number of blocks, and slices of columns in a cell.
BLOCK_SHINGLES, BLOCKS, SLICES = 1 << 20, 16, 4
#: Bytes of the dense rows, and gathered columns, that are in memory at once inside a cell.
DENSE, GATHER = 16 << 20, 1 << 22
#: Rows of a column that are paired in one block when it is paired exactly.
COLUMN_ROWS = 1000
#: Shingles that a task holds while it counts.
CHUNK = 2_000_000
#: Sets that a task remembers so as to emit the columns of equal ones once.
SEEN = 1 << 17


def text_sets(data: np.ndarray, offsets: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct shingle hashes of every text of a block, and the bounds of each text's part."""
    words = Words(data, offsets, BLANK_SPLIT)
    token, fits = shingles(words, k)
    parts = []
    for a, b in zip(words.bounds[:-1].tolist(), words.bounds[1:].tolist(), strict=True):
        if b - a >= k:
            parts.append(np.unique(token[a : b - k + 1]))
        elif b > a:
            parts.append(np.array([sequence_hash(words.hash[a:b])], np.uint64))
        else:
            parts.append(token[:0])
    return np.concatenate(parts), np.append(0, np.cumsum([len(p) for p in parts]))


def _signatures(tokens: np.ndarray, bounds: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Two 64-bit sums over each set, which together identify it."""
    sums = []
    for salt in (0x1234567, 0x89ABCDEF01):
        total = np.append(np.uint64(0), np.cumsum(mix(tokens ^ np.uint64(salt)), dtype=np.uint64))
        sums.append(total[bounds[1:]] - total[bounds[:-1]])
    return sums[0], sums[1]


def _parity(tokens: np.ndarray, bounds: np.ndarray) -> list[np.ndarray]:
    """Parity words of each set; two sets' words differ in at most as many bits as the sets differ in shingles."""
    bit = np.uint64(1) << (tokens & np.uint64(63))
    word = (tokens >> np.uint64(6)) % np.uint64(PARITY)
    out = []
    for k in range(PARITY):
        run = np.append(np.uint64(0), np.bitwise_xor.accumulate(np.where(word == k, bit, np.uint64(0))))
        out.append((run[bounds[1:]] ^ run[bounds[:-1]]).view(np.int64))
    return out


_BITS = [f"p{k}" for k in range(PARITY)]


def _profile(text_col: str, id_col: str, k: int):
    """One row per document (id, size, signature) and one per locally frequent column (token, documents)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[np.ndarray] = []
        seen: set = set()
        names = ["column", "id", "n", "s1", "s2", *_BITS]

        def frequent() -> pa.RecordBatch:
            token, n = np.unique(np.concatenate(held) if held else np.zeros(0, np.uint64), return_counts=True)
            token, n = token[n >= LOCAL_LEAST], n[n >= LOCAL_LEAST]
            held.clear()
            seen.clear()
            none = pa.nulls(len(token), pa.int64())
            return pa.RecordBatch.from_arrays([pa.array(np.ones(len(token), bool)), none, pa.array(n.astype(np.int64)), pa.array(token.view(np.int64)), none, *[none] * PARITY], names=names)

        size = 0
        for rows, data, offsets in blocks(batches, text_col):
            tokens, bounds = text_sets(data, offsets, k)
            s1, s2 = _signatures(tokens, bounds)
            n = np.diff(bounds)
            for i, key in enumerate(zip(s1.tolist(), s2.tolist(), strict=True)):
                if key not in seen:
                    seen.add(key)
                    held.append(tokens[bounds[i] : bounds[i + 1]])
                    size += int(n[i])
            yield pa.RecordBatch.from_arrays([pa.array(np.zeros(len(n), bool)), rows.column(rows.schema.get_field_index(id_col)), pa.array(n), pa.array(s1.view(np.int64)), pa.array(s2.view(np.int64)), *map(pa.array, _parity(tokens, bounds))], names=names)
            if size >= CHUNK:
                yield frequent()
                size = 0
        yield frequent()

    return run


def _postings(text_col: str, id_col: str, k: int, percent: int, order_of):
    """(key, id, packed) for the columns among which two similar documents must share one; equal sets of a task once.

    The key is the token, salted for hot columns; salt, size and position are packed into one number.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tokens_of, counts = order_of()
        table = Lookup(tokens_of)
        seen: set = set()
        for rows, data, offsets in blocks(batches, text_col):
            tokens, bounds = text_sets(data, offsets, k)
            s1, s2 = _signatures(tokens, bounds)
            at, known = table.find(tokens)
            rank = np.where(known, counts[at], 0) if len(counts) else np.zeros(len(tokens), np.int64)
            who = rows.column(rows.schema.get_field_index(id_col))
            there, ids = who.is_valid().to_numpy(zero_copy_only=False), pc.fill_null(who, 0).to_numpy()
            out: list[tuple] = []
            for i in range(len(ids)):
                a, b = int(bounds[i]), int(bounds[i + 1])
                key = (int(s1[i]), int(s2[i]))
                if a == b or key in seen or not there[i]:
                    continue
                seen.add(key)
                n = b - a
                p = n - -(-percent * n // 100) + 1
                r = rank[a:b]
                first = np.flatnonzero(r == 0)[:p]  # tokens are sorted, so these are in order
                if len(first) < p:
                    rest = np.flatnonzero(r)
                    first = np.concatenate([first, rest[np.lexsort((tokens[a:b][rest], r[rest]))][: p - len(first)]])
                out.append((tokens[a:b][first], np.full(p, ids[i], np.int64), np.full(p, n, np.int64), np.arange(p), r[first] >= HOT))
            if len(seen) > SEEN:
                seen.clear()
            if out:
                token, who, n, pos, hot = (np.concatenate(x) for x in zip(*out, strict=True))
                salt = np.where(hot, 1 + who % SALTS, 0)
                yield pa.record_batch({"key": pa.array(token.view(np.int64) ^ (salt << 40)), "id": pa.array(who), "packed": pa.array(salt << 56 | n << 28 | pos)})

    return run


def _possible(a: str, b: str, percent: int) -> Column:
    """Sizes and positions of a shared column allow the similarity (if it is the first one shared)."""
    c = lambda s, x: F.col(f"{s}.{x}")
    need = F.ceil(F.lit(percent) * (c(a, "n") + c(b, "n")) / F.lit(100 + percent))
    sizes = (100 * F.least(c(a, "n"), c(b, "n")) >= percent * F.greatest(c(a, "n"), c(b, "n")))
    return sizes & (F.least(c(a, "n") - c(a, "pos"), c(b, "n") - c(b, "pos")) >= need)


def _near(a: str, b: str, percent: int) -> Column:
    """The parity bits that differ are no more than the shingles in which similar sets of these sizes may differ."""
    differ = sum((F.bit_count(F.col(f"{a}.{p}").bitwiseXOR(F.col(f"{b}.{p}"))) for p in _BITS[1:]), F.bit_count(F.col(f"{a}.{_BITS[0]}").bitwiseXOR(F.col(f"{b}.{_BITS[0]}"))))
    return differ * (100 + percent) <= (100 - percent) * (F.col(f"{a}.n") + F.col(f"{b}.n"))


def _near_pairs(pairs: DataFrame, profile: DataFrame, percent: int) -> DataFrame:
    """The pairs (a, b) whose parity bits allow the similarity, so that the sets of the others never move."""
    involved = small_side(materialise(pairs.select(F.col("a").alias("id")).unionByName(pairs.select(F.col("b").alias("id"))).distinct(), "near-ids"))
    marks = materialise(profile.select("id", "n", *_BITS).join(involved, "id", "left_semi").dropDuplicates(["id"]), "marks")
    x, y = (small_side(marks.select(F.col("id").alias(c), F.struct("n", *_BITS).alias(s)), MARKS) for c, s in (("a", "x"), ("b", "y")))
    return pairs.join(x, "a").join(y, "b").where(_near("x", "y", percent)).select("a", "b")


def cell_product(ids: np.ndarray, sets: list[np.ndarray], a: np.ndarray, b: np.ndarray, percent: int) -> np.ndarray:
    """Which of the entries (a, b), given as ids, reach the similarity. ``sets``: the sorted columns of each row."""
    ids, first = np.unique(ids, return_index=True)
    size = np.array([len(sets[i]) for i in first], np.int64)
    column, at, rows_of = np.unique(np.concatenate([sets[i] for i in first]), return_inverse=True, return_counts=True)
    row = np.repeat(np.arange(len(ids)), size)
    common = rows_of > 1  # a column of one row adds to no overlap
    number, inside = np.cumsum(common) - 1, common[at]
    row, col, columns = row[inside], number[at[inside]], int(common.sum())
    cuts = np.linspace(0, columns, SLICES + 1).astype(np.int64)
    start = np.searchsorted(row * columns + col, np.arange(len(ids)) * columns + cuts[:, None])  # (slice, row)
    x, y = np.searchsorted(ids, a), np.searchsorted(ids, b)
    degree = np.bincount(np.concatenate([x, y]), minlength=len(ids))
    x, y = np.where(degree[x] >= degree[y], x, y), np.where(degree[x] >= degree[y], y, x)
    need = -(-percent * (size[x] + size[y]) // (100 + percent))
    overlap, live = np.zeros(len(x), np.int64), np.argsort(x, kind="stable")
    for s in range(SLICES):
        to_come = start[-1] - start[s]
        live = live[overlap[live] + np.minimum(to_come[x[live]], to_come[y[live]]) >= need[live]]
        width = int(cuts[s + 1] - cuts[s])
        if not len(live) or not width:
            continue
        dense_rows, place = np.unique(x[live], return_inverse=True)
        step = max(1, DENSE // width)
        for r in range(0, len(dense_rows), step):
            mine = dense_rows[r : r + step]
            dense = np.zeros((len(mine), width), bool)
            n = start[s + 1][mine] - start[s][mine]
            entry = np.repeat(start[s][mine] - np.cumsum(n) + n, n) + np.arange(n.sum())
            dense[np.repeat(np.arange(len(mine)), n), col[entry] - cuts[s]] = True
            lo, hi = np.searchsorted(place, [r, r + step])
            length = start[s + 1][y[live[lo:hi]]] - start[s][y[live[lo:hi]]]
            parts = np.unique(np.append(np.searchsorted(np.cumsum(length), np.arange(0, length.sum() + GATHER, GATHER)), hi - lo))
            for p, q in zip(parts[:-1], parts[1:], strict=True):
                which, n = live[lo + p : lo + q], length[p:q]
                end = np.cumsum(n)
                entry = np.repeat(start[s][y[which]] - end + n, n) + np.arange(n.sum())
                hits = np.append(0, np.cumsum(dense[np.repeat(place[lo + p : lo + q] - r, n), col[entry] - cuts[s]]))
                overlap[which] += hits[end] - hits[end - n]
    return overlap >= need


def _links(pairs: DataFrame, docs: DataFrame, id_col: str, text_col: str, k: int, percent: int, mean: float) -> DataFrame:
    """The entries (a, b) whose overlap reaches the similarity: the product, cell by cell. ``mean``: shingles of a document."""
    wanted_ids = pairs.select(F.explode(F.array("a", "b")).alias("id")).distinct().count()
    count = max(BLOCKS, int(wanted_ids * mean // BLOCK_SHINGLES))
    block = lambda c: F.pmod(F.xxhash64(c, F.lit(5)), F.lit(count))
    cell = F.least(block("a"), block("b")) * count + F.greatest(block("a"), block("b"))
    dealt = pairs.select(cell.alias("cell"), "a", "b")
    wanted = dealt.select(F.explode(F.array("a", "b")).alias("id"), "cell").groupBy("id").agg(F.collect_set("cell").alias("cells"))
    texts = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text")).join(small_side(materialise(wanted, "wanted")), "id")

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sent: set = set()  # repeated rows of an id go once from a task
        for rows, data, offsets in blocks(batches):
            ids = rows.column(0).to_pylist()
            fresh = [i for i, x in enumerate(ids) if x not in sent and not sent.add(x)]
            if fresh:
                tokens, bounds = text_sets(data, offsets, k)
                yield pa.record_batch({"id": rows.column(0).take(fresh), "cells": rows.column(2).take(fresh), "tokens": pa.array([tokens[bounds[i] : bounds[i + 1]].tobytes() for i in fresh], pa.binary())})

    sets = texts.mapInArrow(pack, "id long, cells array<long>, tokens binary").select(F.explode("cells").alias("cell"), "id", "tokens")

    def product(entries: pa.Table, rows: pa.Table) -> pa.Table:
        if not entries.num_rows:
            return entries.select(["a", "b"])
        sets = [np.frombuffer(t.as_buffer(), np.uint64) for t in rows.column("tokens")]
        found = cell_product(rows.column("id").to_numpy(), sets, entries.column("a").to_numpy(), entries.column("b").to_numpy(), percent)
        return entries.select(["a", "b"]).filter(pa.array(found))

    made = dealt.groupBy("cell").cogroup(sets.groupBy("cell")).applyInArrow(product, "a long, b long")
    return materialise(made, "jaccard-links")


def _split(columns: DataFrame) -> DataFrame:
    """A row of a column for each part over which the column's rows are dealt (``salt``: 0, or 1 to SALTS for a ``hot`` one)."""
    return columns.withColumn("salt", F.explode(F.when(F.col("hot"), F.sequence(F.lit(1), F.lit(SALTS))).otherwise(F.array(F.lit(0))))).drop("hot")


def frequent_columns(counts: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """Tokens and counts above one frequency, chosen so that they are at most MOST_FREQUENT; sorted by token.

    The frequency comes from a histogram (eight bars for each doubling).
    """
    bar = F.floor(8 * F.log2("n"))
    held, least = 0, None
    for r in sorted(counts.groupBy(bar.alias("bar")).agg(F.count(F.lit(1)).alias("columns")).collect(), reverse=True):
        held += r["columns"]
        if held > MOST_FREQUENT:
            break
        least = r["bar"]
    if least is None:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64)
    got = counts.where(bar >= least).toArrow()
    token, n = got.column("token").to_numpy().view(np.uint64), got.column("n").to_numpy()
    place = np.argsort(token)
    return token[place], n[place]


def _pairs(joined: DataFrame) -> DataFrame:
    return joined.select(F.least("x.id", "y.id").alias("a"), F.greatest("x.id", "y.id").alias("b")).distinct()


def similarity_classes(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", k: int = 4, percent: int = 85) -> DataFrame:
    """One row per input row: id, ``n_shingles``, ``component_id`` (smallest id reachable by links of at least ``percent`` per cent)."""
    sc = docs.sparkSession.sparkContext
    base = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text"))
    schema = T.StructType([T.StructField("column", T.BooleanType()), *(T.StructField(c, T.LongType()) for c in ("id", "n", "s1", "s2", *_BITS))])
    rows = materialise(base.mapInArrow(_profile("text", "id", k), schema), "profile")
    profile = rows.where("NOT column").drop("column")
    order = sc.broadcast(frequent_columns(materialise(rows.where("column").groupBy(F.col("s1").alias("token")).agg(F.sum("n").alias("n")), "frequent")))
    mean = profile.agg(F.coalesce(F.avg("n"), F.lit(0.0))).first()[0]

    # Equal sets are one class; classes of very many documents are decided where they are read.
    signed = materialise(profile.select("id", "n", F.unhex(F.concat(*[F.lpad(F.hex(c), 16, "0") for c in ("s1", "s2")])).alias("digest")), "signed")
    members = materialise(group_digests(signed, pick=F.min).select("id", "n", F.when(F.col("n") > 0, F.col("keep_id")).alias("rep")), "classes")

    # One shuffle of the necessary columns; hot ones are salted, so a key's group stays small. Leaders are chosen in the same pass.
    postings = spread(base.mapInArrow(_postings("text", "id", k, percent, lambda: order.value), "key long, id long, packed long"), "key")
    group = Window.partitionBy("key")
    me = F.struct("id", "packed")
    leader = lambda seed: F.min_by(me, F.xxhash64("id", F.lit(seed))).over(group).alias(f"l{seed}")
    led = postings.select("key", "id", "packed", F.count(F.lit(1)).over(group).alias("m"), leader(1), leader(2)).where((F.col("m") > 1) | (F.shiftright("packed", 56) > 0))
    token = F.col("key").bitwiseXOR(F.shiftleft(F.shiftright("packed", 56), 40)).alias("token")
    # Two rows, or three with two leaders: the leaders meet every pair of the column.
    settled = (F.shiftright("packed", 56) == 0) & ((F.col("m") == 2) | ((F.col("m") == 3) & (F.col("l1.id") != F.col("l2.id"))))
    columns = materialise(led.select(token, "id", "packed", *[F.col(f"l{s}.{c}").alias(f"{c}{s}") for s in (1, 2) for c in ("id", "packed")], (~settled).alias("open")), "columns")

    moved = small_side(materialise(members.where("id <> rep").select("id", "rep").distinct(), "copies"))
    reps = lambda df, c: df.join(moved.withColumnsRenamed({"id": c, "rep": f"{c}_rep"}), c, "left").withColumn(c, F.coalesce(f"{c}_rep", c)).drop(f"{c}_rep")
    field = lambda c, at: F.shiftright(c, at).bitwiseAND(F.lit((1 << 28) - 1))
    side = lambda i, p: F.struct(F.col(i).alias("id"), field(p, 28).alias("n"), field(p, 0).alias("pos"))
    with_leaders = columns.select(side("id", "packed").alias("x"), F.explode(F.array(side("id1", "packed1"), side("id2", "packed2"))).alias("y"))
    near = with_leaders.where((F.col("x.id") != F.col("y.id")) & _possible("x", "y", percent)).select(F.least("x.id", "y.id").alias("a"), F.greatest("x.id", "y.id").alias("b")).distinct()
    near = reps(reps(materialise(near, "near"), "a"), "b").where("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()
    tried = materialise(_near_pairs(materialise(near, "near-reps"), profile, percent), "leader-pairs")
    found = small_side(materialise(components(_links(tried, base, "id", "text", k, percent, mean)), "components"))

    # A column is open if its documents are not all in one component yet.
    component = lambda df, c, out: df.join(found.withColumnsRenamed({"id": c, "component": out}), c, "left").withColumn(out, F.coalesce(out, c))
    odd_of = lambda rows: rows.groupBy("token", "hot").agg(F.min("c").alias("lo"), F.max("c").alias("hi")).where("lo <> hi").select("token", "hot")
    salt = F.shiftright("packed", 56).cast("int")
    asked = columns.where("open").withColumn("salt", salt).withColumn("hot", F.col("salt") > 0)
    labelled = component(component(reps(reps(asked.select("token", "hot", "id", "id1"), "id"), "id1"), "id", "c"), "id1", "c1")
    odd = labelled.where((F.col("c") != F.col("c1")) & ~F.col("hot")).select("token", "hot").unionByName(odd_of(labelled.where("hot")))
    open_columns = small_side(materialise(_split(odd.distinct()), "open"))
    open_rows = reps(asked.join(open_columns, ["token", "salt"], "left_semi").select("token", "hot", "id", field("packed", 28).alias("n"), field("packed", 0).alias("pos")), "id")
    part = F.when(F.col("hot"), 1 + F.pmod(F.col("id"), F.lit(SALTS))).otherwise(0).cast("int")
    open_rows = materialise(open_rows.distinct().withColumn("salt", part), "open-rows")

    # Rounds of hubs. They are aggregated before the exchange and sent to every part of a column, so a hot column is no one task's work.
    me = F.struct("id", "n", "pos", "c")
    used = open_rows.select("token", "id").limit(0)
    for _ in range(ROUNDS):
        own = component(open_rows, "id", "c")
        hubs = own.join(used, ["token", "id"], "left_anti").groupBy("token", "hot").agg(F.min_by(me, F.struct(F.col("pos") / F.col("n"), "id")).alias("y"))
        hubs = materialise(hubs, "hubs")
        used = used.unionByName(hubs.select("token", "y.id"))
        met = own.select("token", "salt", me.alias("x")).join(small_side(materialise(_split(hubs), "hub-parts")), ["token", "salt"]).where((F.col("x.c") != F.col("y.c")) & _possible("x", "y", percent)).select(F.least("x.id", "y.id").alias("a"), F.greatest("x.id", "y.id").alias("b")).distinct()
        fresh = materialise(_near_pairs(materialise(met.join(tried, ["a", "b"], "left_anti"), "near"), profile, percent), "round-pairs")
        stars = found.where("id <> component").select(F.col("id").alias("a"), F.col("component").alias("b"))
        found = small_side(materialise(components(stars.unionByName(_links(fresh, base, "id", "text", k, percent, mean))), "components"))
        tried = tried.unionByName(fresh)

    # The rest of the open columns, exactly: blocks of the documents outside a column's largest component against blocks of all.
    listed = materialise(component(open_rows, "id", "c"), "open-labels")
    listed = listed.join(small_side(materialise(_split(odd_of(listed)), "open")), ["token", "salt"], "left_semi")
    sizes = listed.groupBy("token", "hot", "c").agg(F.count(F.lit(1)).alias("m"))
    parts = lambda rows: F.greatest(F.ceil(rows / COLUMN_ROWS), F.lit(1)).cast("int")
    main = sizes.groupBy("token", "hot").agg(F.max_by("c", F.struct("m", "c")).alias("main"), parts(F.sum("m") - F.max("m")).alias("minor_parts"), parts(F.sum("m")).alias("all_parts"))
    ids = small_side(materialise(listed.select("id").distinct(), "listed"))
    parity = materialise(profile.join(ids, "id", "left_semi").select("id", *_BITS).dropDuplicates(["id"]), "parity")
    placed = listed.join(small_side(materialise(_split(main), "main")), ["token", "salt"]).join(small_side(parity, MARKS), "id")
    open_lists = materialise(placed.select("token", "id", "n", "pos", "c", "main", "minor_parts", "all_parts", *_BITS), "open-columns")
    place = lambda seed, n: F.pmod(F.xxhash64("id", F.lit(seed)), F.col(n)).cast("int")
    every = lambda n: F.explode(F.sequence(F.lit(0), F.col(n) - 1))
    minor = open_lists.where("c <> main").withColumn("u", place(1, "minor_parts")).withColumn("v", every("all_parts"))
    whole = open_lists.withColumn("v", place(2, "all_parts")).withColumn("u", every("minor_parts"))
    same = (F.col("x.token") == F.col("y.token")) & (F.col("x.u") == F.col("y.u")) & (F.col("x.v") == F.col("y.v"))
    cross = same & (F.col("x.c") != F.col("y.c")) & ((F.col("y.c") == F.col("y.main")) | (F.col("x.id") < F.col("y.id"))) & _possible("x", "y", percent) & _near("x", "y", percent)
    second = _pairs(minor.alias("x").join(whole.alias("y"), cross)).join(tried, ["a", "b"], "left_anti")
    more = _links(materialise(second, "cross-pairs"), base, "id", "text", k, percent, mean)
    stars = found.where("id <> component").select(F.col("id").alias("a"), F.col("component").alias("b"))
    final = small_side(materialise(components(stars.unionByName(more)), "components"))
    out = members.join(final.withColumnRenamed("id", "rep"), "rep", "left")
    return out.select(F.col("id").alias(id_col), F.col("n").alias("n_shingles"), F.coalesce("component", "rep", "id").alias("component_id"))
