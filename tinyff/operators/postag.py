"""Tagging: silver tags by rule, word clusters in a Bloom map, window features, independent token classification."""

from __future__ import annotations

import hashlib
import unicodedata
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import gram_bags
from ..functions.text import sentences, tokens
from ..plans.scratch import BROADCAST_ROWS, materialise
from . import train
from .bloommap import BloomMap, key_hash
from .features import FeatureGroup, Template
from .model import Network
from .train import Bags

#: Fixed lists of frequent function words by language.
FUNCTION_WORDS = {
    "de": "der die und in den von zu das mit sich",
    "en": "the of and to a in is that it for",
    "es": "de la que el en y los se del las",
    "fr": "de la le et les des en un du une",
}
#: Fixed word ends and their tags by language.
SUFFIXES = {
    "de": (("heit", "NOUN"), ("keit", "NOUN"), ("ung", "NOUN"), ("lich", "ADJ")),
    "en": (("ing", "VERB"), ("ed", "VERB"), ("ly", "ADV"), ("ble", "ADJ")),
    "es": (("ción", "NOUN"), ("mente", "ADV"), ("ado", "VERB")),
    "fr": (("tion", "NOUN"), ("ment", "ADV"), ("eau", "NOUN")),
}
OPEN_TAGS = ("NOUN", "VERB", "ADJ", "ADV")
TAGS = ("ADJ", "ADV", "FUNC", "NOUN", "NUM", "PROPN", "PUNCT", "SYM", "VERB")
CLUSTERS, MIN_FREQ = 64, 5


def sentence_rows(docs: DataFrame) -> DataFrame:
    """(sent_id, doc_id, lang, toks): sentences with their tokens in the row; nothing is shuffled."""
    rows = docs.select("doc_id", "lang", F.posexplode(sentences(F.col("text"))).alias("s", "sentence"))
    return rows.select(F.concat_ws("-", "doc_id", "s").alias("sent_id"), "doc_id", "lang", tokens(F.col("sentence")).alias("toks")).where(F.size("toks") > 0)


def token_rows(docs: DataFrame) -> DataFrame:
    """(sent_id, doc_id, lang, pos, tok) with positions from 0."""
    return sentence_rows(docs).select("sent_id", "doc_id", "lang", F.posexplode("toks").alias("pos", "tok"))


def lexicon(docs: DataFrame, min_freq: int = MIN_FREQ, clusters: int = CLUSTERS) -> DataFrame:
    """Constructed word clusters: an arbitrary class for every frequent word (word, freq, cluster)."""
    words = token_rows(docs).select(F.lower("tok").alias("word")).where(F.col("word").rlike(r"^\p{L}+$"))
    counts = words.groupBy("word").agg(F.count(F.lit(1)).alias("freq")).where(F.col("freq") >= min_freq)
    return counts.withColumn("cluster", F.pmod(F.conv(F.substring(F.md5("word"), 1, 8), 16, 10).cast("long"), F.lit(clusters)))


def token_counts(sents: DataFrame) -> DataFrame:
    """(tok, n): tokens of sentence rows, counted where they are; the rows of one token are not added up."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            counted = batch.column(0).flatten().value_counts()
            yield pa.RecordBatch.from_arrays([counted.field(0), counted.field(1)], names=["tok", "n"])

    return sents.select("toks").mapInArrow(run, "tok string, n long")


def sentence_lexicon(sents: DataFrame, min_freq: int = MIN_FREQ, clusters: int = CLUSTERS) -> DataFrame:
    """The same rows as ``lexicon``, from sentence rows."""
    words = token_counts(sents).select(F.lower("tok").alias("word"), "n").where(F.col("word").rlike(r"^\p{L}+$"))
    counts = words.groupBy("word").agg(F.sum("n").alias("freq")).where(F.col("freq") >= min_freq)
    return counts.withColumn("cluster", F.pmod(F.conv(F.substring(F.md5("word"), 1, 8), 16, 10).cast("long"), F.lit(clusters)))


def neighbour_signature(sents: DataFrame, frequent: int = 30) -> DataFrame:
    """Distributional clusters of sentence rows: (word, cluster) by the commonest left and right neighbour among the most frequent words.

    Neighbours are counted where a sentence is; no token is shuffled.
    """
    counts = materialise(token_counts(sents).groupBy("tok").agg(F.sum("n").alias("n")), "token-counts")
    top = counts.groupBy(F.lower("tok").alias("word")).agg(F.sum("n").alias("n")).orderBy(F.desc("n"), "word").limit(frequent).select("word")
    forms = {r["tok"]: r["word"] for r in counts.withColumn("word", F.lower("tok")).join(F.broadcast(top), "word").collect()}  # spellings of ``frequent`` words

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words = sorted(set(forms.values()))
        number, names = {w: i for i, w in enumerate(words)}, pa.array(words, pa.string())
        for batch in batches:
            toks = batch.column(0).flatten().dictionary_encode()
            at, size = toks.indices.to_numpy().astype(np.int64), np.diff(batch.column(0).offsets.to_numpy())
            top = np.fromiter((number[forms[w]] if w in forms else -1 for w in toks.dictionary.to_pylist()), np.int64, len(toks.dictionary))[at]
            inside = np.ones(len(at), bool)
            inside[np.append(0, np.cumsum(size))[:-1][size > 0]] = False  # places with a token before them
            here = np.flatnonzero(inside)
            for left, word, near in ((True, here, here - 1), (False, here - 1, here)):
                some = top[near] >= 0
                cell, n = np.unique(at[word[some]] * len(words) + top[near[some]], return_counts=True)
                arrays = [toks.dictionary.take(pa.array(cell // max(1, len(words)))), pa.array(np.full(len(cell), left)), names.take(pa.array(cell % max(1, len(words)))), pa.array(n.astype(np.int64))]
                yield pa.RecordBatch.from_arrays(arrays, names=["tok", "before", "near", "n"])

    made = sents.select("toks").mapInArrow(run, "tok string, before boolean, near string, n long")
    n = made.groupBy(F.lower("tok").alias("word"), "before", "near").agg(F.sum("n").alias("n"))
    best = lambda side: F.min_by(F.when(side, F.col("near")), F.when(side, F.struct(-F.col("n"), F.col("near"))))
    both = n.groupBy("word").agg(best(F.col("before")).alias("left"), best(~F.col("before")).alias("right"))
    return both.select("word", F.concat_ws("|", F.coalesce("left", F.lit("-")), F.coalesce("right", F.lit("-"))).alias("cluster"))


def _by_language(table: dict[str, Column], other: Column) -> Column:
    out = other
    for lang, c in table.items():
        out = F.when(F.col("lang") == lang, c).otherwise(out)
    return out


def _chain(cases: list[tuple[Column, Column]], last: Column) -> Column:
    out = last
    for when, then in reversed(cases):
        out = F.when(when, then).otherwise(out)
    return out


#: Words whose tokens are never shuffled: the most frequent ones, whose clusters every task holds.
HEAD_WORDS = 10_000


def _with_cluster(rows: DataFrame, lex: DataFrame) -> DataFrame:
    """Adds ``cluster`` by word from a written lexicon: broadcast if it is small.

    A larger one is split: tokens of the most frequent words are joined to a broadcast head, so that
    no frequent word's tokens meet in one task, and the rest is shuffled by word.
    """
    table = lex.select("word", "cluster")
    if table.count() <= BROADCAST_ROWS // 4:
        return rows.join(F.broadcast(table), "word", "left")  # at most half a million words
    head = F.broadcast(lex.orderBy(F.desc("freq"), "word").limit(HEAD_WORDS).select("word", "cluster", F.lit(True).alias("_head")))
    first = rows.join(head, "word", "left")
    tail = first.where("_head IS NULL").drop("cluster").join(table, "word", "left")
    cols = [*rows.columns, "cluster"]
    return first.where("_head").select(*cols).unionByName(tail.select(*cols))


def silver_tags(docs: DataFrame, lex: DataFrame) -> DataFrame:
    """Token rows with ``tag``: form, function words, word ends, context, and the lexical class of frequent words."""
    return tag_rows(token_rows(docs), lex)


def tag_rows(rows: DataFrame, lex: DataFrame) -> DataFrame:
    """The same for given token rows."""
    rows = _with_cluster(rows.withColumn("word", F.lower("tok")), lex)
    is_func = _by_language({k: F.col("word").isin(v.split()) for k, v in FUNCTION_WORDS.items()}, F.lit(False))
    at = Window.partitionBy("sent_id").orderBy("pos")
    rows = rows.withColumn("func", is_func).withColumn("prev_func", F.coalesce(F.lag("func").over(at), F.lit(False)))
    none = F.lit(None).cast("string")
    end = _by_language({k: _chain([(F.col("word").endswith(s), F.lit(t)) for s, t in v], none) for k, v in SUFFIXES.items()}, none)
    open_tag = lambda n: F.element_at(F.array(*map(F.lit, OPEN_TAGS)), (F.pmod(n, F.lit(4)) + 1).cast("int"))
    tail = F.conv(F.substring(F.md5(F.substring("word", -2, 2)), 1, 8), 16, 10).cast("long")
    tag = _chain(
        [
            (F.col("tok").rlike(r"^[0-9]+$"), F.lit("NUM")),
            (F.col("tok").isin(*".,;:!?"), F.lit("PUNCT")),
            (~F.col("tok").rlike(r"^\p{L}+$"), F.lit("SYM")),
            (F.col("func"), F.lit("FUNC")),
            ((F.col("pos") > 0) & F.col("tok").rlike(r"^\p{Lu}"), F.lit("PROPN")),
            (end.isNotNull(), end),
            (F.col("prev_func"), F.lit("NOUN")),
            (F.col("cluster").isNotNull(), open_tag(F.col("cluster"))),
        ],
        open_tag(tail),
    )
    return rows.select("sent_id", "doc_id", "lang", "pos", "tok", "cluster", tag.alias("tag"))


def tagged_sentences(tagged: DataFrame) -> DataFrame:
    """(sent_id, lang, toks, tags, clusters): one row per sentence, in order."""
    cell = F.struct("pos", "tok", "tag", F.coalesce("cluster", F.lit(-1)).alias("cluster"))
    rows = tagged.groupBy("sent_id", "doc_id", "lang").agg(F.array_sort(F.collect_list(cell)).alias("cells"))
    return rows.select("sent_id", "doc_id", "lang", F.col("cells.tok").alias("toks"), F.col("cells.tag").alias("tags"), F.col("cells.cluster").alias("clusters"))


class SilverTagger:
    """``silver_tags`` of whole batches of sentences: what a tag needs of a word is worked out once for every distinct word."""

    #: Distinct words that a worker remembers.
    ROOM = 1 << 18

    def __init__(self, lex: dict[str, int]):
        self.lex, self.langs, self.seen, self.rows = lex, list(FUNCTION_WORDS), {}, np.zeros((0, 12), np.int16)
        self.func = {k: frozenset(v.split()) for k, v in FUNCTION_WORDS.items()}
        self.any_func, self.any_end = frozenset().union(*self.func.values()), tuple({x for v in SUFFIXES.values() for x, _ in v})
        self.number, self.last = {t: i for i, t in enumerate(TAGS)}, {}

    def _row(self, tok: str) -> list[int]:
        """Fixed tag or -1, capital, tag of the last letters, cluster, and for each language: function word, tag of the word end or -1."""
        kind = unicodedata.category(tok[0])
        if kind[0] != "L":
            fixed = "NUM" if tok.isascii() and tok.isdigit() else "PUNCT" if tok in ".,;:!?" else "SYM"
            return [self.number[fixed], 0, 0, -1, 0, 0, 0, 0, -1, -1, -1, -1]
        word = tok.lower()
        last = self.last.get(word[-2:])
        if last is None:
            last = self.last[word[-2:]] = self.number[OPEN_TAGS[int(hashlib.md5(word[-2:].encode()).hexdigest()[:8], 16) % 4]]
        func = [word in self.func[k] for k in self.langs] if word in self.any_func else [0, 0, 0, 0]
        ends = [-1, -1, -1, -1]
        if word.endswith(self.any_end):
            ends = [next((self.number[t] for x, t in SUFFIXES[k] if word.endswith(x)), -1) for k in self.langs]
        return [-1, kind == "Lu", last, self.lex.get(word, -1), *func, *ends]

    def _places(self, words: list[str]) -> np.ndarray:
        """Rows of distinct words."""
        if len(self.seen) + len(words) > self.ROOM:
            self.seen, self.rows = {}, self.rows[:0]
        fresh = [w for w in words if w not in self.seen]
        if fresh:
            self.seen.update(zip(fresh, range(len(self.seen), len(self.seen) + len(fresh)), strict=True))
            self.rows = np.concatenate([self.rows, np.array([self._row(w) for w in fresh], np.int16)])
        return np.fromiter(map(self.seen.__getitem__, words), np.int64, len(words))

    def __call__(self, toks: pa.ListArray, langs: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
        """Numbers in TAGS, and clusters (-1: none), of all tokens side by side."""
        held = toks.flatten().dictionary_encode()
        at = self._places(held.dictionary.to_pylist())[held.indices.to_numpy()]
        size = np.diff(toks.offsets.to_numpy())
        first = np.zeros(len(at), bool)
        first[(np.cumsum(size) - size)[size > 0]] = True
        number = {k: i for i, k in enumerate(self.langs)}
        lang = np.repeat(np.array([number.get(x, -1) for x in langs], np.int64), size)
        fixed, capital, last, cluster = (self.rows[at, i] for i in range(4))
        func = (lang >= 0) & (self.rows[at, 4 + lang] > 0)
        end = np.where(lang >= 0, self.rows[at, 8 + lang], -1)
        before = np.append(False, func[:-1])[: len(func)] & ~first
        opened = np.array([TAGS.index(t) for t in OPEN_TAGS])
        chain = [(fixed >= 0, fixed), (func, TAGS.index("FUNC")), (~first & (capital > 0), TAGS.index("PROPN")), (end >= 0, end), (before, TAGS.index("NOUN")), (cluster >= 0, opened[cluster % 4])]
        return np.select([c for c, _ in chain], [t for _, t in chain], last), cluster


def silver_sentences(sents: DataFrame, lex: DataFrame) -> DataFrame:
    """The same rows as ``tagged_sentences`` of ``silver_tags``, with the other columns of the sentence rows kept.

    Sentences stay where they are, and a written lexicon of up to half a million words is broadcast; with a
    larger one the relational form is taken.
    """
    if lex.count() > BROADCAST_ROWS // 4:
        rows = sents.select("doc_id", "lang", "sent_id", F.posexplode("toks").alias("pos", "tok"))
        return sents.drop("doc_id", "lang", "toks").join(tagged_sentences(tag_rows(rows, lex)), "sent_id")
    held = sents.sparkSession.sparkContext.broadcast({r["word"]: r["cluster"] for r in lex.select("word", "cluster").collect()})

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tagger, names = SilverTagger(held.value), pa.array(TAGS)
        for batch in batches:
            toks = batch.column("toks")
            tags, clusters = tagger(toks, batch.column("lang").to_pylist())
            off = pa.array(np.append(0, np.cumsum(np.diff(toks.offsets.to_numpy()))).astype(np.int32))
            lists = [pa.ListArray.from_arrays(off, x) for x in (names.take(pa.array(tags)), pa.array(clusters.astype(np.int64)))]
            yield pa.RecordBatch.from_arrays([*batch.columns, *lists], names=[*batch.schema.names, "tags", "clusters"])

    schema = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in sents.schema.fields) + ", tags array<string>, clusters array<long>"
    return sents.mapInArrow(run, schema)


# Features: character n-grams of the words in a three-word window, ends and shape of the focus word.


def template(dim: int = 16, clusters: bool = False, cluster_dim: int = 8) -> Template:
    groups = [FeatureGroup("bigrams", 1000, dim, slots=3, n=2), FeatureGroup("trigrams", 2000, dim, slots=1, n=3), FeatureGroup("ends", 1000, dim, slots=2, kind="affix"), FeatureGroup("shape", 32, max(2, dim // 4), slots=1, kind="shape")]
    if clusters:
        groups.append(FeatureGroup("clusters", CLUSTERS + 2, cluster_dim, slots=3, kind="cluster"))
    return Template(tuple(groups))


def _shape(word: str) -> int:
    return (word[:1].isupper() << 0) | (word.isupper() << 1) | (word.isdigit() << 2) | (word.isalpha() << 3) | ((len(word) == 1) << 4)


def slot_groups(t: Template) -> list[int]:
    return [i for i, g in enumerate(t.groups) for _ in range(g.slots)]


def end_bags(ends: list[str], size: int) -> tuple[np.ndarray, np.ndarray]:
    """The bucket of each whole word end (of any length), as bags of one."""
    ids = np.zeros(len(ends), np.int64)
    length = np.fromiter(map(len, ends), np.int64, len(ends))
    for n in np.unique(length):
        at = np.flatnonzero(length == n)
        ids[at] = gram_bags([ends[i] for i in at], int(n), size)[0]
    return ids, np.arange(len(ends) + 1)


class Words:
    """The distinct words of many sentences, their features computed once, and the place of every token among them."""

    def __init__(self, sents: list[list[str]], t: Template, clusters: BloomMap | None = None):
        size = np.fromiter(map(len, sents), np.int64, len(sents))
        flat = np.empty(int(size.sum()) + 1, object)
        flat[0], flat[1:] = "\x00", [w for s in sents for w in s]  # the first stands outside sentences
        at, words = pd.factorize(flat)
        self.at = at[1:]
        start = np.zeros(len(self.at) + 1, bool)
        start[np.append(0, np.cumsum(size))] = True
        self.before = np.where(start[:-1], 0, np.append(0, self.at[:-1])[: len(self.at)])
        self.after = np.where(start[1:], 0, np.append(self.at[1:], 0)[: len(self.at)])
        low = [w.lower() for w in words]
        wrapped, v = [f"^{w}$" for w in low], [g.vocab for g in t.groups]
        self.bags = [gram_bags(wrapped, 2, v[0]), gram_bags(wrapped, 3, v[1]), end_bags(["^" + w[:3] for w in low], v[2]), end_bags([w[-3:] + "$" for w in low], v[2]), (np.fromiter(map(_shape, words), np.int64, len(words)), np.arange(len(words) + 1))]
        self.groups = [0, 1, 2, 2, 3]
        if len(t.groups) > 4:
            known = clusters.find(key_hash(low)) + 2
            known[0] = 0
            self.bags.append((known, np.arange(len(words) + 1)))
            self.groups.append(4)

    def slots(self) -> list[tuple[int, np.ndarray]]:
        """For each slot of the template: which bag it reads, at which words."""
        around = (self.before, self.at, self.after)
        out = [(0, a) for a in around] + [(k, self.at) for k in (1, 2, 3, 4)]
        return out + [(5, a) for a in around] * (len(self.bags) > 5)

    def token_bags(self, t: Template) -> Bags:
        made = [Bags([0], [self.bags[k][0]], [self.bags[k][1]]).take(a) for k, a in self.slots()]
        return Bags(slot_groups(t), [m.ids[0] for m in made], [m.offsets[0] for m in made])

    def h0(self, net: Network) -> np.ndarray:
        """The inputs of all tokens: every distinct word is embedded once."""
        rows = [train.embed(net, Bags([g], [ids], [off])) for g, (ids, off) in zip(self.groups, self.bags, strict=True)]
        return np.concatenate([rows[k][a] for k, a in self.slots()], 1)


def build(rows: list[dict], dev: list[dict], dim: int = 16, clusters: BloomMap | None = None, hidden: int = 64, epochs: int = 3, seed: int = 0) -> Network:
    """Learns from sentences (``toks``, ``tags``). ``clusters``: the map whose values are features; its bytes count as the model's."""
    t = template(dim, clusters is not None)
    index = {tag: i for i, tag in enumerate(TAGS)}
    data = [(Words([r["toks"] for r in part], t, clusters).token_bags(t), np.array([index[x] for r in part for x in r["tags"]])) for part in (rows, dev)]
    net, _ = train.sgd(Network.random(t, hidden, list(TAGS), seed=dim + seed), *data[0], train.Settings(lr=0.1, epochs=epochs, seed=1 + seed), data[1])
    if clusters is not None:
        net.resources |= {"clusters": clusters, "bytes": clusters.bytes}
    return net


class Tagger:
    """Tags of many sentences: the share of a distinct word in the hidden layer, as the word before, in and after the focus, is computed once and remembered."""

    #: Distinct words that a worker remembers.
    ROOM = 1 << 16

    def __init__(self, net: Network):
        self.net, self.seen, self.classes = net, {}, pa.array(net.classes)
        self._clear()

    def _clear(self) -> None:
        self.seen = {"\x00": 0}  # stands outside sentences
        self.shares = self._share(["\x00"])

    def _share(self, words: list[str]) -> np.ndarray:
        """(word, place, hidden) for the places before, in and after the focus."""
        net = self.net
        made, out = Words([words], net.template, net.resources.get("clusters")), np.zeros((3, len(words), len(net.c)), np.float32)
        rows = [train.embed(net, Bags([g], [ids], [off])) for g, (ids, off) in zip(made.groups, made.bags, strict=True)]
        a = 0
        for place, k in [(0, 0), (1, 0), (2, 0), (1, 1), (1, 2), (1, 3), (1, 4)] + [(0, 5), (1, 5), (2, 5)] * (len(rows) > 5):
            b = a + rows[k].shape[1]
            out[place] += (rows[k] @ net.w[:, a:b].T)[made.at]
            a = b
        return out.transpose(1, 0, 2)

    def _places(self, words: list[str]) -> np.ndarray:
        """Rows of distinct words in ``shares``."""
        if len(self.seen) + len(words) > self.ROOM:
            self._clear()
        fresh = [w for w in words if w not in self.seen]
        if fresh:
            self.seen.update(zip(fresh, range(len(self.seen), len(self.seen) + len(fresh)), strict=True))
            self.shares = np.concatenate([self.shares, self._share(fresh)])
        return np.fromiter(map(self.seen.__getitem__, words), np.int64, len(words))

    def best(self, toks: pa.Array, size: np.ndarray, block: int = 1 << 13) -> np.ndarray:
        """The class of every token; ``toks``: the tokens of sentences of ``size`` tokens side by side."""
        held = toks.dictionary_encode()
        at = self._places(held.dictionary.to_pylist())[held.indices.to_numpy()]
        n, edge = len(at), np.zeros(len(at) + 1, bool)
        edge[np.append(0, np.cumsum(size))] = True
        before = np.where(edge[:-1], 0, np.append(0, at[:-1])[:n])
        after = np.where(edge[1:], 0, np.append(at[1:], 0)[:n])
        out, net = np.zeros(n, np.int64), self.net
        for a in range(0, n, block):
            cut = slice(a, a + block)
            h = self.shares[:, 1][at[cut]]
            h += self.shares[:, 0][before[cut]]
            h += self.shares[:, 2][after[cut]]
            h += net.c
            out[cut] = (np.maximum(h, 0, out=h) @ net.beta.T + net.b).argmax(1)
        return out


def predict(sents: DataFrame, net: Network, keep: list[str], out: str = "pred", more: dict[str, tuple] | None = None) -> DataFrame:
    """``keep`` columns and the predicted tags of every sentence; the tokens of many sentences form one matrix.

    ``more``: further columns, by name the type and a function of a batch of ``keep`` columns and tokens.
    """
    more = more or {}
    held = sents.sparkSession.sparkContext.broadcast(net)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tagger = Tagger(held.value)
        for batch in batches:
            size = np.diff(batch.column("toks").offsets.to_numpy())
            tags = tagger.classes.take(pa.array(tagger.best(batch.column("toks").flatten(), size)))
            made = pa.ListArray.from_arrays(pa.array(np.append(0, np.cumsum(size)).astype(np.int32)), tags)
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in keep), made, *(make(batch) for _, make in more.values())], names=[*keep, out, *more])

    schema = ", ".join(f"{c} {sents.schema[c].dataType.simpleString()}" for c in keep) + f", {out} array<string>" + "".join(f", {c} {kind}" for c, (kind, _) in more.items())
    return sents.select(*dict.fromkeys([*keep, "toks"])).mapInArrow(run, schema)


def tag_all(net: Network, sents: list[list[str]], tagger: Tagger | None = None) -> list[np.ndarray]:
    size = np.fromiter(map(len, sents), np.int64, len(sents))
    if not size.sum():
        return [np.zeros(0, object) for _ in sents]
    best = (tagger or Tagger(net)).best(pa.array([w for s in sents for w in s], pa.string()), size)
    return np.split(np.array(net.classes, object)[best], np.cumsum(size)[:-1])


def unigram_tagger(tagged: DataFrame, key: str = "tok") -> DataFrame:
    """(word, best): the most frequent tag of each word; ties go to the first tag."""
    n = tagged.groupBy(F.lower(key).alias("word"), "tag").agg(F.count(F.lit(1)).alias("n"))
    return n.groupBy("word").agg(F.min_by("tag", F.struct(-F.col("n"), F.col("tag"))).alias("best"))
