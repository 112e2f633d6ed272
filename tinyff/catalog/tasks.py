"""The four tasks: gold data, baselines and exact checks in SQL, and trained runs."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import text
from ..operators import bloommap, bytespan, cost, forward, langid, metrics, pipelines, postag, preorder, quantize, segment, splits, train
from ..plans.scratch import materialise, spread
from ..registry import query
from ..sources.tables import load
from .core import BUCKET, MODEL, docs

# --- language identification -------------------------------------------------

MD5 = "('0x' || substr(md5({x}), 1, 8))::BIGINT"

for _w in (5, 10, 20, 50):
    _room = f"greatest(length(text) - {_w}, 0)"

    def _fragments(spark, d, w=_w):
        return langid.fragments(docs(spark, d), w)

    _start = MD5.format(x=f"doc_id::VARCHAR || ':{_w}:' || k::VARCHAR") + f" % ({_room} + 1) + 1"
    query(f"fragments_{_w}", f"SELECT doc_id, k, substr(text, {_start}, {_w}) AS frag, lang FROM (SELECT *, unnest(range(0, CASE WHEN {_room} > 0 THEN 5 ELSE 1 END)) AS k FROM documents)")(_fragments)


def _profile_sql() -> str:
    parts = " UNION ALL ".join(f"SELECT doc_id, {' || '.join(f'c[i + {k}]' if k else 'c[i]' for k in range(n))} AS x FROM (SELECT doc_id, c, unnest(range(1, len(c) - {n - 2})) AS i FROM c)" for n in (1, 2, 3))
    return f"""c AS (SELECT doc_id, regexp_extract_all(lower(text), '(?s).') AS c FROM documents), g AS ({parts}),
    p AS (SELECT doc_id, {BUCKET.format(x='x', v=1000)} AS v, count(*) AS cnt FROM g GROUP BY 1, 2),
    s AS (SELECT doc_id, lang, {MD5.format(x="doc_id::VARCHAR")} % 100 AS h FROM documents)"""


def _split_profiles(spark, d):
    base = docs(spark, d)
    prof = materialise(langid.profile(base, "doc_id", "text"), "profiles")
    known = base.where(splits.hash_percent(F.col("doc_id")) < 80).select("doc_id", "lang")
    rest = base.where(splits.hash_percent(F.col("doc_id")) >= 80).select("doc_id", "lang")
    return prof, known, rest


@query("prototype_profile", f"WITH {_profile_sql()} SELECT lang, v, sum(cnt)::BIGINT AS cnt FROM p JOIN s USING (doc_id) WHERE h < 80 GROUP BY ALL")
def prototype_profile(spark, d):
    prof, known, _ = _split_profiles(spark, d)
    return langid.prototypes(prof, known, "doc_id", "lang").select("lang", F.col("v").cast("long").alias("v"), "cnt")


@query(
    "prototype_label",
    f"""WITH {_profile_sql()}, t AS (SELECT lang, v, sum(cnt)::BIGINT AS pc FROM p JOIN s USING (doc_id) WHERE h < 80 GROUP BY ALL),
    n AS (SELECT lang, sqrt(sum(pc * pc)) AS norm FROM t GROUP BY lang),
    k AS (SELECT p.doc_id, t.lang, round(sum(cnt * pc) / any_value(norm), 6) AS sim FROM p JOIN s USING (doc_id) JOIN t ON p.v = t.v JOIN n ON n.lang = t.lang WHERE h >= 80 GROUP BY 1, 2)
    SELECT doc_id, lang AS label FROM k QUALIFY row_number() OVER (PARTITION BY doc_id ORDER BY sim DESC, lang) = 1""",
)
def prototype_label(spark, d):
    prof, known, rest = _split_profiles(spark, d)
    return langid.nearest_prototype(prof.join(rest, "doc_id", "left_semi"), langid.prototypes(prof, known, "doc_id", "lang"), "doc_id", "lang")


@query(
    "neighbor_label",
    f"""WITH {_profile_sql()}, a AS (SELECT p.* FROM p JOIN s USING (doc_id) WHERE h >= 80), b AS (SELECT p.* FROM p JOIN s USING (doc_id) WHERE h < 80),
    n AS (SELECT doc_id, sqrt(sum(cnt * cnt)) AS norm FROM b GROUP BY 1),
    k AS (SELECT a.doc_id, b.doc_id AS other, round(sum(a.cnt * b.cnt) / any_value(norm), 6) AS sim FROM a JOIN b USING (v) JOIN n ON n.doc_id = b.doc_id GROUP BY 1, 2)
    SELECT k.doc_id, s.lang AS label FROM k JOIN s ON s.doc_id = k.other QUALIFY row_number() OVER (PARTITION BY k.doc_id ORDER BY sim DESC, other) = 1""",
)
def neighbor_label(spark, d):
    test, known = _neighbour_sides(docs(spark, d))
    return langid.nearest_neighbour(test, known, known.select("doc_id", "lang"), "doc_id", "lang").select("doc_id", "label")


def _neighbour_sides(base: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Written profiles of the documents that ask and of those that are known."""
    rows = materialise(langid.sparse_profiles(base.withColumn("h", splits.hash_percent(F.col("doc_id"))), ["doc_id", "lang", "h"], "text"), "sparse-profiles")
    return rows.where("h >= 80"), rows.where("h < 80")


@query("neighbor_bands")
def neighbor_bands(spark, d):
    """Bucketed neighbours: how many queries get one, how often its label is right, and how often it is as near as the exact one (recall)."""
    asked, every = _neighbour_sides(docs(spark, d))
    rest, known = asked.select("doc_id", "lang"), every.select("doc_id", "lang")
    got = langid.neighbour_by_bands(asked, every, "doc_id")
    got = got.join(known.select(F.col("doc_id").alias("other"), F.col("lang").alias("label")), "other").select("doc_id", "label", F.col("sim").alias("near"))
    exact = langid.nearest_neighbour(asked, every, every.select("doc_id", "lang"), "doc_id", "lang").select("doc_id", "sim")
    both = rest.join(exact, "doc_id", "left").join(got, "doc_id", "left")
    right = lambda c: F.avg(F.coalesce(c, F.lit(False)).cast("double"))
    return both.agg(F.count(F.lit(1)).alias("queries"), F.count("label").alias("answered"), F.avg((F.col("label") == F.col("lang")).cast("double")).alias("accuracy"), right(F.abs(F.col("near") - F.col("sim")) < 2e-6).alias("recall"))


_SHARE = "x AS (SELECT p.doc_id, v, cnt, cnt / (sum(cnt) OVER (PARTITION BY p.doc_id)) AS share, row_number() OVER (PARTITION BY p.doc_id ORDER BY cnt DESC, v) AS r FROM p JOIN s USING (doc_id) WHERE h >= 80)"
_CLASS = "t AS (SELECT lang, v, sum(cnt)::BIGINT AS c FROM p JOIN s USING (doc_id) WHERE h < 80 GROUP BY ALL), y AS (SELECT l.lang, b.v, coalesce(c, 0) AS c FROM (SELECT DISTINCT lang FROM t) l CROSS JOIN (SELECT unnest(range(0, 1000)) AS v) b LEFT JOIN t ON t.lang = l.lang AND t.v = b.v), q AS (SELECT lang, v, c / (sum(c) OVER (PARTITION BY lang)) AS q, row_number() OVER (PARTITION BY lang ORDER BY c DESC, v) AS pr FROM y)"

for _sim, _part in (("skew", "share * ln(share / (0.99::DOUBLE * q + (1 - 0.99::DOUBLE) * share))"), ("rank", "abs(r - pr)")):

    def _nearest(spark, d, sim=_sim):
        prof, known, rest = _split_profiles(spark, d)
        return langid.nearest_prototype(prof.join(rest, "doc_id", "left_semi"), langid.prototypes(prof, known, "doc_id", "lang"), "doc_id", "lang", sim)

    query(f"prototype_label_{_sim}", f"WITH {_profile_sql()}, {_SHARE}, {_CLASS}, k AS (SELECT doc_id, lang, round(sum({_part}), 6) AS worse FROM x JOIN q ON x.v = q.v GROUP BY 1, 2) SELECT doc_id, lang AS label FROM k QUALIFY row_number() OVER (PARTITION BY doc_id ORDER BY worse, lang) = 1")(_nearest)


_W = "(((7 * v + 3 * k) % 11 - 5) / 10.0::DOUBLE)"


@query(
    "softmax_sql_step",
    f"""WITH c AS (SELECT doc_id, regexp_extract_all(lower(text), '(?s).') AS c FROM documents), g AS (SELECT doc_id, unnest(c) AS x FROM c),
    p AS (SELECT doc_id, {BUCKET.format(x='x', v=16)} AS v, count(*) AS cnt FROM g GROUP BY 1, 2), f AS (SELECT doc_id, v, cnt / (sum(cnt) OVER (PARTITION BY doc_id)) AS x FROM p),
    n AS (SELECT lang AS class, row_number() OVER (ORDER BY lang) - 1 AS k FROM (SELECT DISTINCT lang FROM documents)), w AS (SELECT class, v, {_W} AS w FROM n, (SELECT unnest(range(0, 16)) AS v)),
    z AS (SELECT doc_id, class, sum(x * w) AS z FROM f JOIN w USING (v) GROUP BY 1, 2), e AS (SELECT doc_id, class, exp(z - max(z) OVER (PARTITION BY doc_id)) AS e FROM z),
    d AS (SELECT doc_id, class, e / (sum(e) OVER (PARTITION BY doc_id)) - (class = lang)::INT AS d FROM e JOIN documents USING (doc_id)),
    gr AS (SELECT class, v, sum(x * d) / (SELECT count(*) FROM documents) AS g FROM f JOIN d USING (doc_id) GROUP BY 1, 2)
    SELECT class, v::BIGINT AS v, round(coalesce(g, 0), 7)::DOUBLE AS grad, round(w - 0.5 * coalesce(g, 0), 7)::DOUBLE AS w FROM w LEFT JOIN gr USING (class, v)""",
)
def softmax_sql_step(spark, d):
    """A gradient step of a softmax layer over 16 character buckets, from weights given by a formula."""
    base = docs(spark, d)
    prof = langid.profile(base, "doc_id", "text", (1,), 16)
    x = prof.withColumn("x", F.col("cnt") / F.sum("cnt").over(Window.partitionBy("doc_id"))).select("doc_id", "v", "x")
    classes = [r[0] for r in base.select("lang").distinct().orderBy("lang").collect()]
    w = spark.createDataFrame([(c, v, ((7 * v + 3 * k) % 11 - 5) / 10) for k, c in enumerate(classes) for v in range(16)], "class string, v int, w double")
    done = train.sql_step(materialise(x, "features"), base.select("doc_id", "lang"), w, "doc_id", "lang", 0.5)
    return done.select("class", F.col("v").cast("long").alias("v"), F.round("grad", 7).alias("grad"), F.round("w", 7).alias("w"))


@query("majority_label", f"WITH s AS (SELECT doc_id, lang, {MD5.format(x='doc_id::VARCHAR')} % 100 AS h FROM documents) SELECT doc_id, (SELECT lang FROM s WHERE h < 80 GROUP BY lang ORDER BY count(*) DESC, lang LIMIT 1) AS label FROM s WHERE h >= 80")
def majority_label(spark, d):
    base = docs(spark, d).select("doc_id", "lang", splits.hash_percent(F.col("doc_id")).alias("h"))
    top = base.where("h < 80").groupBy("lang").agg(F.count(F.lit(1)).alias("n")).agg(F.min_by("lang", F.struct(-F.col("n"), F.col("lang"))).alias("label"))
    return base.where("h >= 80").crossJoin(F.broadcast(top)).select("doc_id", "label")  # a single row


@query("normalised_text", r"SELECT doc_id, md5(trim(regexp_replace(regexp_replace(regexp_replace(regexp_replace(text, '<[^>]*>', ' ', 'g'), 'https?://[^ ]+', ' ', 'g'), '[#$%&*|!]+', ' ', 'g'), '[ \t\n]+', ' ', 'g'))) AS digest FROM documents")
def normalised_text(spark, d):
    return docs(spark, d).select("doc_id", F.md5(text.normalise(F.col("text"))).alias("digest"))


@query(
    "pages_visible_text",
    r"SELECT page_id, md5(trim(regexp_replace(regexp_replace(regexp_replace(regexp_replace(html, '(?s)<script.*?</script>|<style.*?</style>|<!--.*?-->', ' ', 'g'), '<[^>]*>', ' ', 'g'), '&[a-z]+;', ' ', 'g'), '[ \t\n\r]+', ' ', 'g'))) AS digest FROM pages",
)
def pages_visible_text(spark, d):
    return load(spark, d, "pages").select("page_id", F.md5(text.visible_text(F.col("html"))).alias("digest"))


def _langid_samples(spark, d, per_class=150, label="lang"):
    parts = langid.split_docs(docs(spark, d))
    return parts, langid.sample(parts, "train", per_class, 1, label), langid.sample(parts, "dev", 40, 2, label)


def _test_fragments(parts: DataFrame) -> DataFrame:
    test = parts.where("part = 'test'")
    cut = [langid.fragments(test, w).withColumn("width", F.lit(w)) for w in (5, 10, 20, 50)]
    out = test.select("doc_id", F.lit(0).cast("long").alias("k"), F.col("text").alias("frag"), "lang", F.lit(0).alias("width"))
    for c in cut:
        out = out.unionByName(c)
    return out.select("lang", "width", "frag")


def _judge(tests: DataFrame, nets: dict) -> DataFrame:
    """(model, width, n, micro_f1, agree, kb, flops) by one pass for all networks; width 0 is the whole text, agree: labels equal to the first network's."""
    got = langid.score_all(tests, list(nets.values()), "frag", ["lang", "width"])
    rows = got.select("lang", "width", F.col("labels")[0].alias("first"), F.posexplode("labels").alias("i", "label"))
    equal = lambda c: F.round(F.avg((F.col("label") == F.col(c)).cast("double")), 6)
    sums = rows.groupBy("i", "width").agg(F.count(F.lit(1)).alias("n"), equal("lang").alias("micro_f1"), equal("first").alias("agree"))
    shape = [(i, name, round(cost.size_kb(net), 1), cost.net_flops(net)) for i, (name, net) in enumerate(nets.items())]
    about = tests.sparkSession.createDataFrame(shape, "i int, model string, kb double, flops long")
    return sums.join(F.broadcast(about), "i").select("model", "width", "n", "micro_f1", "agree", "kb", "flops")  # one row a network


@query("langid_trained")
def langid_trained(spark, d):
    """Six and sixteen dimensions, in 8-bit codes that are decoded as they are read, and summed instead of averaged, on fragments of all widths."""
    parts, tr, dev = _langid_samples(spark, d)
    six, sixteen = langid.build(tr, dev, 6), langid.build(tr, dev, 16)
    summed = langid.build(tr, dev, 16, combine="sum")
    return _judge(_test_fragments(parts), {"16 dims": sixteen, "6 dims": six, "16 dims, 8 bits": quantize.coded(sixteen), "16 dims, summed": summed})


@query("langid_bits")
def langid_bits(spark, d):
    """The sixteen-dimensional model at 16, 8, 4 and 2 bits, and at 4 bits by granularity and width of the scales: score and labels that stay the same."""
    parts, tr, dev = _langid_samples(spark, d)
    net = langid.build(tr, dev, 16)
    nets = {"32 bits": net} | {f"{b} bits": quantize.coded(net, b) for b in (16, 8, 4, 2)}
    nets |= {f"4 bits, {g} scales of {np.dtype(t).itemsize} bytes": quantize.coded(net, 4, t, g) for g in ("row", "group", "matrix") for t in (np.float16, np.float32) if (g, t) != ("row", np.float16)}
    return _judge(_test_fragments(parts), nets)


@query("langid_budget")
def langid_budget(spark, d):
    """Dimensions against bits where sizes are about equal: a network of few exact dimensions, and of more dimensions in codes."""
    parts, tr, dev = _langid_samples(spark, d)
    shapes = ((6, 32), (10, 16), (16, 8), (24, 4), (32, 2))
    return _judge(_test_fragments(parts), {f"{dim} dims, {bits} bits": net if bits == 32 else quantize.coded(net, bits) for dim, bits in shapes for net in [langid.build(tr, dev, dim)]})


@query("langid_orders")
def langid_orders(spark, d):
    """Subsets of the n-gram lengths: each alone, those up to a length, and all but one."""
    parts, tr, dev = _langid_samples(spark, d)
    subsets = [(1, 2, 3, 4), (1,), (2,), (3,), (4,), (1, 2), (1, 2, 3), (2, 3, 4), (1, 3, 4), (1, 2, 4)]
    size = dict(zip(langid.ORDERS, langid.VOCAB, strict=True))
    return _judge(_test_fragments(parts), {str(o): langid.build(tr, dev, 16, orders=o, vocab=tuple(size[n] for n in o), epochs=2) for o in subsets})


@query("langid_grid")
def langid_grid(spark, d):
    """Grid search: a Spark task per trial over one broadcast sample of bounded size."""
    _, tr, dev = _langid_samples(spark, d, 60)
    t = langid.template(8)
    start = langid.Network.random(t, 64, tr.classes)
    return train.grid(spark, start, langid.bags(tr.texts, t), tr.labels, (langid.bags(dev.texts, t), dev.labels), train.Settings(epochs=2))


@query("langid_local_sgd")
def langid_local_sgd(spark, d):
    """Data-parallel training on fragments of all widths of all training documents, by rounds of local steps and averaging."""
    parts = langid.split_docs(docs(spark, d))
    classes = [r[0] for r in parts.where("lang IS NOT NULL").select("lang").distinct().orderBy("lang").collect()]
    t, known = langid.template(8), parts.where("part = 'train' AND lang IS NOT NULL")
    rows = langid.fragments(known, 10).unionByName(langid.fragments(known, 20)).unionByName(langid.fragments(known, 50)).unionByName(langid.fragments(known, 5))
    rows = materialise(rows.select("frag", "lang").repartition(4), "fragments")

    def featurize(batch: pd.DataFrame):
        return langid.bags(batch["frag"], t), np.array([classes.index(x) for x in batch["lang"]])

    net = train.local_sgd(rows, langid.Network.random(t, 64, classes), featurize, train.Settings(average=False), rounds=4)
    return _judge(_test_fragments(parts), {"local SGD": net})


@query("langid_baselines")
def langid_baselines(spark, d):
    """Nearest prototype by three measures, nearest neighbour and the majority, learned from all training documents, on the same fragments as the networks."""
    parts = langid.split_docs(docs(spark, d))
    known = parts.where("part = 'train' AND lang IS NOT NULL").select(F.col("doc_id").alias("fid"), "text", "lang")
    test = materialise(_test_fragments(materialise(parts.where("part = 'test'"), "test")).withColumn("fid", F.xxhash64("frag")), "fragments")
    asked = test.select("fid", "frag").dropDuplicates(["fid"])  # equal fragments ask once and are joined back to all rows
    ask, rows = (materialise(langid.sparse_profiles(x, k, c), "sparse") for x, k, c in ((asked, ["fid"], "frag"), (known, ["fid", "lang"], "text")))
    labels = rows.select("fid", "lang")
    protos = materialise(langid.prototypes(rows, labels, "fid", "lang"), "prototypes")
    got = {"nearest prototype" + (f", {sim}" if sim != "cosine" else ""): langid.nearest_prototype(ask, protos, "fid", "lang", sim) for sim in ("cosine", "skew", "rank")}
    got["nearest neighbour"] = langid.nearest_neighbour(ask, rows, labels, "fid", "lang").select("fid", "label")
    top = labels.groupBy("lang").agg(F.count(F.lit(1)).alias("n")).agg(F.min_by("lang", F.struct(-F.col("n"), F.col("lang"))).alias("label"))
    got["majority"] = asked.select("fid").crossJoin(F.broadcast(top))  # a single row
    out = None
    for name, g in got.items():
        row = test.join(g, "fid", "left").groupBy("width").agg(F.count(F.lit(1)).alias("n"), F.avg(F.coalesce(F.col("label") == F.col("lang"), F.lit(False)).cast("double")).alias("micro_f1")).withColumn("model", F.lit(name))
        out = row if out is None else out.unionByName(row)
    return out


@query("langid_transfer")
def langid_transfer(spark, d):
    """The model on other tables, normalised first: pages (their lang attribute as weak label), conversations, benchmark passages."""
    _, tr, dev = _langid_samples(spark, d)
    net = langid.build(tr, dev, 16, epochs=3)
    pages = load(spark, d, "pages").select(F.lit("pages").alias("tab"), F.nullif(F.regexp_extract("html", r'lang="([a-z]+)"', 1), F.lit("")).alias("weak"), text.visible_text(F.col("html")).alias("t"))
    talk = load(spark, d, "conversations").select(F.lit("conversations").alias("tab"), F.lit(None).cast("string").alias("weak"), F.col("text").alias("t"))
    bench = load(spark, d, "benchmark").select(F.lit("benchmark").alias("tab"), F.lit(None).cast("string").alias("weak"), F.col("text").alias("t"))
    got = langid.score(pages.unionByName(talk).unionByName(bench), net, "t", ["tab", "weak"], preprocess=text.normalise)
    return got.groupBy("tab", "label").agg(F.count(F.lit(1)).alias("n"), F.avg((F.col("weak") == F.col("label")).cast("double")).alias("agrees"))


@query("other_targets")
def other_targets(spark, d):
    """The same network on quality and toxicity labels."""
    out = None
    for target in ("quality", "toxic"):
        base = docs(spark, d).join(load(spark, d, "labels"), "doc_id").withColumn("target", F.col(target).cast("string"))
        parts = langid.split_docs(base)
        tr, dev = (langid.sample(parts, p, 150, 3, "target", (200, 800)) for p in ("train", "dev"))
        net = langid.build(tr, dev, 8, hidden=32, epochs=3)
        got = langid.score(parts.where("part = 'test'").select("target", "text"), net, "text", ["target"])
        row = metrics.per_class(got, "target", "label").withColumn("task", F.lit(target))
        out = row if out is None else out.unionByName(row)
    return out


@query("embedding_quantization")
def embedding_quantization(spark, d):
    """Nearest class mean of real vectors before and after coding: labels that agree, by bits."""
    emb = load(spark, d, "embeddings").select("vec_id", "label", F.col("embedding").alias("w"))
    out = None
    for bits in (8, 4, 2):
        q = quantize.decode(quantize.encode(emb, bits=bits)).select("vec_id", "label", F.transform("w", lambda x: x.cast("double")).alias("w"), "restored")
        best = {}
        for col in ("w", "restored"):
            cells = q.select("vec_id", "label", F.posexplode(col).alias("i", "x"))
            means = cells.groupBy("label", "i").agg(F.avg("x").alias("m")).withColumnRenamed("label", "class")
            d2 = cells.join(F.broadcast(means), "i").groupBy("vec_id", "class").agg(F.sum((F.col("x") - F.col("m")) ** 2).alias("d"))  # classes x 64 rows
            best[col] = d2.groupBy("vec_id").agg(F.min_by("class", F.struct(F.round("d", 9), "class")).alias(col))
        row = best["w"].join(best["restored"], "vec_id").agg(F.lit(bits).alias("bits"), F.count(F.lit(1)).alias("n"), F.avg((F.col("w") == F.col("restored")).cast("double")).alias("agree"))
        out = row if out is None else out.unionByName(row)
    return out


# --- tagging -------------------------------------------------------------------

SENT = r"""s0 AS (SELECT doc_id, lang, list_filter(string_split(regexp_replace(coalesce(text, ''), '\. ', '.' || chr(10), 'g'), chr(10)), lambda x: length(trim(x)) > 0) AS ss FROM documents),
s1 AS (SELECT doc_id, lang, unnest(range(0, len(ss))) AS s, unnest(ss) AS sentence FROM s0),
s AS (SELECT doc_id || '-' || s AS sent_id, doc_id, lang, sentence, regexp_extract_all(sentence, '[\p{L}]+|[0-9]+|[^\s\p{L}0-9]') AS toks FROM s1),
t AS (SELECT sent_id, doc_id, lang, unnest(range(0, len(toks))) AS pos, unnest(toks) AS tok FROM s)"""
LEX = f"lex AS (SELECT lower(tok) AS word, count(*) AS freq, {MD5.format(x='lower(tok)')} % 64 AS cluster FROM t WHERE regexp_full_match(lower(tok), '\\p{{L}}+') GROUP BY lower(tok) HAVING count(*) >= 5)"


def _silver_sql() -> str:
    func = " ".join(f"WHEN lang = '{k}' THEN word IN ({', '.join(repr(w) for w in v.split())})" for k, v in postag.FUNCTION_WORDS.items())
    end = " ".join(f"WHEN lang = '{k}' THEN CASE {' '.join(f'''WHEN ends_with(word, '{s}') THEN '{t}' ''' for s, t in v)} END" for k, v in postag.SUFFIXES.items())
    tags = "['" + "', '".join(postag.OPEN_TAGS) + "']"
    return rf"""{SENT}, {LEX},
    a AS (SELECT t.*, lower(tok) AS word, cluster FROM t LEFT JOIN lex ON lex.word = lower(tok)),
    b AS (SELECT *, CASE {func} ELSE false END AS func, CASE {end} END AS stem FROM a),
    c AS (SELECT *, coalesce(lag(func) OVER (PARTITION BY sent_id ORDER BY pos), false) AS prev_func FROM b),
    tagged AS (SELECT sent_id, doc_id, lang, pos, tok, cluster, CASE WHEN regexp_full_match(tok, '[0-9]+') THEN 'NUM' WHEN tok IN ('.', ',', ';', ':', '!', '?') THEN 'PUNCT'
      WHEN NOT regexp_full_match(tok, '\p{{L}}+') THEN 'SYM' WHEN func THEN 'FUNC' WHEN pos > 0 AND regexp_matches(tok, '^\p{{Lu}}') THEN 'PROPN' WHEN stem IS NOT NULL THEN stem
      WHEN prev_func THEN 'NOUN' WHEN cluster IS NOT NULL THEN {tags}[(cluster % 4 + 1)::INT] ELSE {tags}[({MD5.format(x="right(word, 2)")} % 4 + 1)::INT] END AS tag FROM c)"""


SILVER = _silver_sql()


def _silver(spark, d, base=None):
    base = docs(spark, d) if base is None else base
    return postag.silver_tags(base, materialise(postag.lexicon(base), "lexicon"))


@query("sentences_tokens", f"WITH {SENT} SELECT doc_id, count(DISTINCT sent_id) AS sentences, count(*) AS tokens FROM t GROUP BY doc_id")
def sentences_tokens(spark, d):
    rows = postag.sentence_rows(docs(spark, d)).groupBy("doc_id").agg(F.count(F.lit(1)).alias("sentences"), F.sum(F.size("toks")).alias("tokens"))
    return rows


@query(
    "window_features",
    f"WITH {SENT}, w AS (SELECT lower(tok) AS cur, lag(lower(tok), 1, '') OVER (PARTITION BY sent_id ORDER BY pos) AS prev, lead(lower(tok), 1, '') OVER (PARTITION BY sent_id ORDER BY pos) AS next FROM t) SELECT {BUCKET.format(x='prev', v=50)} AS prev, {BUCKET.format(x='cur', v=50)} AS cur, {BUCKET.format(x='next', v=50)} AS next, count(*) AS n FROM w GROUP BY ALL",
)
def window_features(spark, d):
    at = Window.partitionBy("sent_id").orderBy("pos")
    w = postag.token_rows(docs(spark, d)).select(F.lower("tok").alias("c"), F.lag(F.lower("tok"), 1, "").over(at).alias("p"), F.lead(F.lower("tok"), 1, "").over(at).alias("x"))
    from ..functions.hashing import bucket

    b = lambda c, name: bucket(F.col(c), 50, "md5").cast("long").alias(name)
    return w.groupBy(b("p", "prev"), b("c", "cur"), b("x", "next")).agg(F.count(F.lit(1)).alias("n"))


@query("silver_tags", f"WITH {SILVER} SELECT doc_id, tag, count(*) AS n, sum(pos * length(tok))::BIGINT AS mark FROM tagged GROUP BY ALL")
def silver_tags(spark, d):
    return _silver(spark, d).groupBy("doc_id", "tag").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("pos") * F.length("tok")).alias("mark"))


_UNI = "u AS (SELECT word, tag FROM (SELECT lower(tok) AS word, tag, count(*) AS n FROM tagged GROUP BY ALL) QUALIFY row_number() OVER (PARTITION BY word ORDER BY n DESC, tag) = 1)"


@query("unigram_tagger", f"WITH {SILVER}, {_UNI} SELECT word, tag AS best FROM u")
def unigram_tagger(spark, d):
    return postag.unigram_tagger(_silver(spark, d))


@query("tag_accuracy", f"WITH {SILVER}, {_UNI} SELECT lang, count(*) AS n, round(avg((tagged.tag = u.tag)::INT), 9)::DOUBLE AS accuracy FROM tagged JOIN u ON u.word = lower(tok) GROUP BY lang")
def tag_accuracy(spark, d):
    tagged = materialise(_silver(spark, d), "tagged")
    both = tagged.withColumn("word", F.lower("tok")).join(postag.unigram_tagger(tagged), "word")
    return metrics.accuracy(both, "tag", "best", "lang").withColumn("accuracy", F.round("accuracy", 9))


@query("tag_accuracy_mean", f"WITH {SILVER}, {_UNI}, l AS (SELECT lang, avg((tagged.tag = u.tag)::INT) AS a FROM tagged JOIN u ON u.word = lower(tok) GROUP BY lang) SELECT round(avg(a), 9)::DOUBLE AS accuracy FROM l")
def tag_accuracy_mean(spark, d):
    """The unweighted mean of the languages' accuracies."""
    tagged = materialise(_silver(spark, d), "tagged")
    both = tagged.withColumn("word", F.lower("tok")).join(postag.unigram_tagger(tagged), "word")
    return metrics.accuracy(both, "tag", "best", "lang").agg(F.round(F.avg("accuracy"), 9).alias("accuracy"))


@query("cluster_lexicon", f"WITH {SENT}, {LEX} SELECT word, freq, cluster FROM lex")
def cluster_lexicon(spark, d):
    return postag.lexicon(docs(spark, d))


@query("cluster_plain_size", f"WITH {SENT}, {LEX} SELECT count(*) AS words, sum(octet_length(encode(word)) + length(cluster::VARCHAR) + 2)::BIGINT AS bytes FROM lex")
def cluster_plain_size(spark, d):
    lex = postag.lexicon(docs(spark, d))
    return lex.agg(F.count(F.lit(1)).alias("words"), F.sum(F.octet_length("word") + F.length(F.col("cluster").cast("string")) + 2).alias("bytes"))


@query(
    "cluster_signature",
    f"""WITH {SENT}, w AS (SELECT sent_id, pos, lower(tok) AS word FROM t), top AS (SELECT word FROM w GROUP BY word ORDER BY count(*) DESC, word LIMIT 30),
    n AS (SELECT word, lag(word) OVER (PARTITION BY sent_id ORDER BY pos) AS l, lead(word) OVER (PARTITION BY sent_id ORDER BY pos) AS r FROM w),
    a AS (SELECT word, l FROM (SELECT word, l, count(*) AS c FROM n WHERE l IN (SELECT word FROM top) GROUP BY ALL) QUALIFY row_number() OVER (PARTITION BY word ORDER BY c DESC, l) = 1),
    b AS (SELECT word, r FROM (SELECT word, r, count(*) AS c FROM n WHERE r IN (SELECT word FROM top) GROUP BY ALL) QUALIFY row_number() OVER (PARTITION BY word ORDER BY c DESC, r) = 1)
    SELECT coalesce(a.word, b.word) AS word, coalesce(l, '-') || '|' || coalesce(r, '-') AS cluster FROM a FULL JOIN b ON a.word = b.word""",
)
def cluster_signature(spark, d):
    return postag.neighbour_signature(postag.sentence_rows(docs(spark, d)))


@query("bloom_positions", f"WITH {SENT}, {LEX}, p AS (SELECT ('0x' || substr(md5(i::VARCHAR || ':' || cluster::VARCHAR || '|' || word), 1, 12))::BIGINT % 65536 AS at FROM lex, (SELECT unnest(range(0, 7)) AS i)) SELECT p.at // 64 AS segment, bit_or(1::UBIGINT << (p.at % 64)::UBIGINT)::VARCHAR AS word FROM p GROUP BY 1")
def bloom_positions(spark, d):
    """The set bits of a map with seven hashes in 65,536 bits, by 64-bit segment (unsigned, as text)."""
    lex = postag.lexicon(docs(spark, d)).select(F.concat_ws("|", F.col("cluster").cast("string"), "word").alias("item"), F.explode(F.sequence(F.lit(0), F.lit(6))).alias("i"))
    at = F.pmod(F.conv(F.substring(F.md5(F.concat_ws(":", F.col("i").cast("string"), "item")), 1, 12), 16, 10).cast("long"), F.lit(65536))
    word = F.bit_or(F.expr("shiftleft(1L, cast(at & 63 as int))"))
    return lex.select(at.alias("at")).groupBy(F.shiftright("at", 6).alias("segment")).agg(F.conv(F.hex(word), 16, 10).alias("word"))


@query("cluster_kmeans")
def cluster_kmeans(spark, d):
    """Distributional clusters by k-means over neighbour counts of frequent words: sizes of the clusters."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector

    rows = postag.token_rows(docs(spark, d)).withColumn("word", F.lower("tok"))
    counts = materialise(rows.groupBy("word").agg(F.count(F.lit(1)).alias("n")), "words")
    top = [r["word"] for r in counts.orderBy(F.desc("n"), "word").limit(20).collect()]
    at = Window.partitionBy("sent_id").orderBy("pos")
    near = rows.select("word", F.lag("word").over(at).alias("l"), F.lead("word").over(at).alias("r"))
    cells = [F.avg((F.col(s) == w).cast("double")) for s in ("l", "r") for w in top]
    vectors = near.join(counts.where("n >= 20").select("word"), "word").groupBy("word").agg(F.transform(F.array(*[F.coalesce(c, F.lit(0.0)) for c in cells]), lambda x: x).alias("v"))
    made = KMeans(k=8, seed=1, maxIter=5, featuresCol="features", predictionCol="cluster").fit(vectors.withColumn("features", array_to_vector("v")))
    return made.transform(vectors.withColumn("features", array_to_vector("v"))).groupBy("cluster").agg(F.count(F.lit(1)).alias("words"))


#: Word types of the published map size.
MAP_TYPES = 250_000


@query("bloom_lookup")
def bloom_lookup(spark, d):
    """Clusters of all word types, and of a sample of 250,000, in both variants and by both hash rules.

    Bits a key, ratio to the plain list, wrong values on stored words, hits on unseen ones.
    """
    every = materialise(postag.lexicon(docs(spark, d), min_freq=1).select("word", "freq", F.col("cluster").alias("value")), "lexicon")
    some = materialise(every.orderBy(F.md5("word"), "word").limit(MAP_TYPES), "lexicon")  # a sample of stated size
    out = None
    for types, lex in (("all types", every), ("250,000 types", some)):
        plain, n = lex.agg(F.sum(F.octet_length("word") + F.length(F.col("value").cast("string")) + 2), F.count(F.lit(1))).first()
        unseen = lex.select(F.concat(F.lit("~"), F.col("word")).alias("word"), F.lit(-1).cast("long").alias("value"))
        for variant, priors in (("pairs", False), ("pairs", True), ("tree", False)):
            held = bloommap.build(lex, "word", "value", 10.0, variant, priors)
            got = bloommap.lookup(lex.select("word", "value").unionByName(unseen), "word", held)
            stored = F.col("value") >= 0
            row = got.agg(
                F.lit(types).alias("types"), F.lit(f"{variant}{', by prior' if priors else ''}").alias("variant"), F.lit(n).alias("words"), F.lit(held.bytes).alias("bytes"), F.lit(8 * held.bytes / n).alias("bits_per_key"), F.lit(plain / held.bytes).alias("smaller_by"),
                F.avg(F.when(stored, F.col("found").isNull().cast("double"))).alias("lost"), F.avg(F.when(stored, (F.col("found") != F.col("value")).cast("double"))).alias("wrong"), F.avg(F.when(~stored, F.col("found").isNotNull().cast("double"))).alias("unseen_hits"),
            )
            out = row if out is None else out.unionByName(row)
    return out


def _tag_samples(spark, d, sentences=500):
    """Tagged sentences split by document; samples of a bounded number of sentences a language for learning; the lexicon."""
    dealt = spread(docs(spark, d).select("doc_id", "lang", "text"), "doc_id")  # a table may be one file of one row group
    rows = materialise(splits.assign(postag.sentence_rows(dealt), "doc_id"), "tokens")
    lex = materialise(postag.sentence_lexicon(rows), "lexicon")
    sents = materialise(postag.silver_sentences(rows, lex), "sentences")
    pick = lambda part, n: [r.asDict() for r in splits.stratified(sents.where((F.col("part") == part) & (F.size("toks") <= 60)), "lang", "sent_id", n).collect()]
    return sents, pick("train", sentences), pick("dev", sentences // 5), lex


def cluster_map(lex: DataFrame) -> bloommap.BloomMap:
    """The Bloom map that a tagger reads its clusters from."""
    return bloommap.build(lex, "word", "cluster", 10.0)


def _neighbour_map(sents: DataFrame) -> bloommap.BloomMap:
    """A map of distributional clusters: the commonest neighbour signatures are clusters 0 to 62, all others 63."""
    words = materialise(postag.neighbour_signature(sents), "signatures")
    top = words.groupBy("cluster").agg(F.count(F.lit(1)).alias("n")).orderBy(F.desc("n"), "cluster").limit(postag.CLUSTERS - 1)
    number = {r["cluster"]: i for i, r in enumerate(top.collect())}
    named = F.create_map(*[F.lit(x) for kv in number.items() for x in kv]) if number else F.create_map().cast("map<string,int>")
    return bloommap.build(words.select("word", F.coalesce(named[F.col("cluster")], F.lit(postag.CLUSTERS - 1)).alias("cluster")), "word", "cluster", 10.0)


def _tagger_scores(test: DataFrame, nets: dict) -> DataFrame:
    """(model, lang, tokens, accuracy, params, kb, flops) by language, and the unweighted mean of the languages as ``mean``."""
    out = None
    for name, net in nets.items():
        got = postag.predict(test, net, ["lang", "tags"])
        right = F.aggregate(F.zip_with("tags", "pred", lambda a, b: (a == b).cast("int")), F.lit(0), lambda a, x: a + x)
        row = materialise(got.groupBy("lang").agg(F.sum(F.size("tags")).alias("tokens"), (F.sum(right) / F.sum(F.size("tags"))).alias("accuracy")), "tag-scores")
        row = row.unionByName(row.agg(F.lit("mean").alias("lang"), F.sum("tokens").alias("tokens"), F.avg("accuracy").alias("accuracy")))
        row = row.select(F.lit(name).alias("model"), "lang", "tokens", "accuracy", F.lit(cost.params(net.template, len(net.c), len(net.classes))).alias("params"), F.lit(round(cost.size_kb(net), 1)).alias("kb"), F.lit(cost.net_flops(net)).alias("flops"))
        out = row if out is None else out.unionByName(row)
    return out


@query("tagger_trained")
def tagger_trained(spark, d):
    """Vanilla, with clusters, half dimensions with clusters, all in 8-bit codes, and the byte-level recurrent network.

    Clusters are read from Bloom maps, which count in KB. The silver tags of frequent words depend on the
    constructed clusters, so that gain is built in; the clusters from neighbours are independent of the tags.
    The recurrent network finds the tokens itself and takes about a thousand training steps, far too few for good spans.
    """
    sents, tr, dev, lex = _tag_samples(spark, d)
    held, near = cluster_map(lex), _neighbour_map(sents)
    nets = {"vanilla": postag.build(tr, dev), "clusters": postag.build(tr, dev, clusters=held), "clusters, half dims": postag.build(tr, dev, 8, clusters=held), "clusters from neighbours": postag.build(tr, dev, clusters=near)}
    test = sents.where("part = 'test'")
    out = _tagger_scores(test, {name: quantize.coded(net) for name, net in nets.items()} | {"vanilla, float": nets["vanilla"]})
    recurrent = bytespan.ByteSpanNetwork(list(postag.TAGS), 48).fit(bytespan.training_data(tr), epochs=10)
    return out.unionByName(_span_scores(test, recurrent))


def _span_scores(test: DataFrame, net: bytespan.ByteSpanNetwork) -> DataFrame:
    """The same columns for the recurrent network; its operations are those of the bytes and symbols of an average token."""
    rows = materialise(bytespan.evaluate(test, net), "span-scores")
    own = rows.select("lang", "tokens", (F.col("right") / F.col("tokens")).alias("accuracy"), (F.col("steps") / F.col("tokens")).alias("steps"))
    own = own.unionByName(own.agg(F.lit("mean").alias("lang"), F.sum("tokens").alias("tokens"), F.avg("accuracy").alias("accuracy"), F.avg("steps").alias("steps")))
    return own.select(F.lit("bytes to spans").alias("model"), "lang", "tokens", "accuracy", F.lit(net.size).alias("params"), F.lit(round(4 * net.size / 1024, 1)).alias("kb"), (F.col("steps") * net.flops(1)).cast("long").alias("flops"))


@query("tagger_per_language")
def tagger_per_language(spark, d):
    """One model for each language in 8-bit codes, against the test sentences of that language."""
    sents, tr, dev, _ = _tag_samples(spark, d, 300)
    out = None
    for lang in sorted({r["lang"] for r in tr}):
        net = quantize.coded(postag.build([r for r in tr if r["lang"] == lang], [r for r in dev if r["lang"] == lang] or dev))
        row = _tagger_scores(sents.where((F.col("part") == "test") & (F.col("lang") == lang)), {"monolingual": net}).where("lang <> 'mean'")
        out = row if out is None else out.unionByName(row)
    return out


@query("byte_lstm_forward")
def byte_lstm_forward(spark, d):
    """The byte-level recurrent baseline's work: a four-layer forward pass over every benchmark passage, bytes and operations."""

    def run(batches):
        rng = np.random.default_rng(1)
        layers = [(rng.normal(0, 0.1, (64, 16)), rng.normal(0, 0.1, (64, 16)), np.zeros(64)) for _ in range(4)]
        table = rng.normal(0, 0.1, (256, 16))
        for batch in batches:
            for i, t in zip(batch["item_id"], batch["text"], strict=True):
                raw = (t or "").encode()
                state = [(np.zeros((1, 16)), np.zeros((1, 16))) for _ in layers]
                for b in raw:
                    x = table[b][None]
                    for k, (w, u, c) in enumerate(layers):
                        state[k] = cost.lstm_cell(x, *state[k], w, u, c)
                        x = state[k][0]
                yield pd.DataFrame({"item_id": [i], "steps": [len(raw)], "flops": [cost.lstm_flops(4, 16, len(raw))], "norm": [float(np.abs(state[-1][0]).sum())]})

    return load(spark, d, "benchmark").mapInPandas(run, "item_id long, steps long, flops long, norm double")


# --- segmentation ----------------------------------------------------------------

WORDS = f"{SENT}, ws AS (SELECT sent_id, lang, list_filter(regexp_split_to_array(sentence, '[ \\t\\n\\r]+'), lambda x: x <> '') AS words FROM s)"


def _words(spark, d, base=None):
    rows = (docs(spark, d) if base is None else base).select("doc_id", "lang", F.posexplode(text.sentences(F.col("text"))).alias("s", "sentence"))
    return rows.select(F.concat_ws("-", "doc_id", "s").alias("sent_id"), "doc_id", "lang", segment.words_of(F.col("sentence")).alias("words"))


_ACT = "array_to_string(list_transform(words, lambda w: 'S' || repeat('M', length(w) - 1)), '')"


@query("seg_gold_actions", f"WITH {WORDS} SELECT sent_id, {_ACT} AS actions FROM ws")
def seg_gold_actions(spark, d):
    return _words(spark, d).select("sent_id", segment.gold_actions(F.col("words")).alias("actions"))


@query("seg_apply", f"WITH {WORDS} SELECT sent_id, array_to_string(words, ' ') AS restored FROM ws")
def seg_apply(spark, d):
    rows = _words(spark, d).select("sent_id", F.array_join("words", "").alias("joined"), segment.gold_actions(F.col("words")).alias("actions"))
    return rows.select("sent_id", segment.apply(F.col("joined"), F.col("actions")).alias("restored"))


@query("seg_ngram_features", f"WITH {WORDS}, c AS (SELECT sent_id, unnest(regexp_extract_all(array_to_string(words, ''), '(?s).')) AS c, unnest(range(0, length(array_to_string(words, '')))) AS i, unnest(regexp_extract_all({_ACT}, '.')) AS a FROM ws), w AS (SELECT coalesce(lag(c) OVER (PARTITION BY sent_id ORDER BY i), '') AS prev, c AS cur, a FROM c) SELECT prev, cur, a AS action, count(*) AS n FROM w GROUP BY ALL")
def seg_ngram_features(spark, d):
    """Counts of (previous character, character, action), in the row: no window over characters is needed."""
    rows = _words(spark, d).select(text.chars(F.array_join("words", "")).alias("c"), text.chars(segment.gold_actions(F.col("words"))).alias("a"))
    shifted = F.concat(F.array(F.lit("")), F.col("c"))
    cells = F.arrays_zip(F.slice(shifted, F.lit(1), F.size("c")).alias("prev"), F.col("c").alias("cur"), F.col("a").alias("action"))
    return rows.select(F.inline(cells)).groupBy("prev", "cur", "action").agg(F.count(F.lit(1)).alias("n"))


@query("seg_vocabulary", f"WITH {WORDS}, c AS (SELECT unnest(regexp_extract_all(array_to_string(words, ''), '(?s).')) AS c FROM ws), f AS (SELECT c, count(*) AS n FROM c GROUP BY c) SELECT CASE WHEN n >= 2 THEN c ELSE '<unknown>' END AS symbol, sum(n)::BIGINT AS n FROM f GROUP BY 1")
def seg_vocabulary(spark, d):
    """Characters; those that occur once are the unknown symbol."""
    c = _words(spark, d).select(F.explode(text.chars(F.array_join("words", ""))).alias("c")).groupBy("c").agg(F.count(F.lit(1)).alias("n"))
    return c.groupBy(F.when(F.col("n") >= 2, F.col("c")).otherwise("<unknown>").alias("symbol")).agg(F.sum("n").alias("n"))


@query("seg_word_f1", f"WITH {WORDS}, k AS (SELECT lang, len(words) AS g, length(array_to_string(words, '')) AS n, list_sum(list_transform(words, lambda w: (length(w) = 1)::INT)) AS ones FROM ws WHERE len(words) > 0) SELECT lang, round(2 * sum((g = 1)::INT) / (count(*) + sum(g)), 9)::DOUBLE AS one_word_f1, round(2 * sum(ones) / (sum(n) + sum(g)), 9)::DOUBLE AS every_char_f1 FROM k GROUP BY lang")
def seg_word_f1(spark, d):
    """Word F1 of the two trivial baselines, by language."""
    ones = F.aggregate("words", F.lit(0), lambda a, w: a + (F.length(w) == 1).cast("int"))
    k = _words(spark, d).where(F.size("words") > 0).select("lang", F.size("words").alias("g"), F.length(F.array_join("words", "")).alias("n"), ones.alias("ones"))
    one = F.round(2 * F.sum((F.col("g") == 1).cast("int")) / (F.count(F.lit(1)) + F.sum("g")), 9)
    return k.groupBy("lang").agg(one.alias("one_word_f1"), F.round(2 * F.sum("ones") / (F.sum("n") + F.sum("g")), 9).alias("every_char_f1"))


def _seg_samples(spark, d, sentences=250):
    words = materialise(splits.assign(_words(spark, d).where(F.size("words") > 0), "doc_id"), "seg-sentences")
    pick = lambda part, n: [r["words"] for r in splits.stratified(words.where((F.col("part") == part) & (F.size("words") <= 60)), "lang", "sent_id", n).collect()]
    return words, pick("train", sentences), pick("dev", sentences // 5)


class _Greedy:
    def __init__(self, net, enc, beam=1):
        self.net, self.enc, self.beam = net, enc, beam

    def __call__(self, texts):
        return segment.decode(texts, self.net, self.enc, self.beam)


class _GreedyKernel(_Greedy):
    def kernel(self):
        return segment.Greedy(self.net, self.enc)


@query("segmenter_trained")
def segmenter_trained(spark, d):
    """Unigrams at 64 and 256 dims, bigrams, hashed characters (in 8-bit codes, vocabularies counted in KB), a beam, and all baselines: decisions and word scores."""
    words, tr, dev = _seg_samples(spark, d)
    test = words.where("part = 'test'")
    made = {"unigrams, 64 dims": segment.build(tr, dev, 64), "unigrams, 256 dims": segment.build(tr, dev, 256), "bigrams, 64 dims": segment.build(tr, dev, 64, bigrams=True), "hashed, 64 dims": segment.build(tr, dev, 64, hashed=True)}
    made = {n: (quantize.coded(net), enc) for n, (net, enc) in made.items()}
    deciders = {n: (_Greedy(*m), cost.size_kb(m[0])) for n, m in made.items()}
    deciders |= {"bigrams, 64 dims, beam": (_Greedy(*made["bigrams, 64 dims"], beam=3), deciders["bigrams, 64 dims"][1])}
    deciders |= {"linear": (segment.LinearSegmenter().fit(tr), None), "linear, conjunctions": (segment.LinearSegmenter(True).fit(tr), None), "longest match": (segment.MaxMatch(tr), None), "one word": (segment.one_word, None), "every character": (segment.every_char, None)}
    out = None
    for name, (decider, kb) in deciders.items():
        row = segment.rates(segment.evaluate(test, decider)).withColumn("model", F.lit(name)).withColumn("kb", F.lit(kb).cast("double"))
        out = row if out is None else out.unionByName(row)
    return out


#: Trials of the structured tasks' grids.
_TRIALS = [{"lr": lr, "momentum": m, "decay": x} for lr in (0.05, 0.1) for m in (0.8, 0.9) for x in (0.9, 0.96)]


@query("segmenter_grid")
def segmenter_grid(spark, d):
    """Grid search of the segmenter by the word F1 of decoded held-out sentences."""
    _, tr, dev = _seg_samples(spark, d, 60)
    net, enc = segment.start(tr, 16, bigrams=True)
    return train.grid(spark, net, *segment.gold_data(tr, enc), segment.gold_data(dev, enc), train.Settings(epochs=1), _TRIALS, segment.word_f1_of(dev, enc))


# --- preordering ------------------------------------------------------------------

ORDER = f"{SILVER}, cl AS (SELECT *, coalesce(sum((tag = 'PUNCT')::INT) OVER (PARTITION BY sent_id ORDER BY pos ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS clause, CASE tag WHEN 'PUNCT' THEN 4 {' '.join(f'''WHEN '{k}' THEN {v}''' for k, v in preorder.CLASS_RANK.items())} END AS class FROM tagged), rk AS (SELECT sent_id, lang, pos, row_number() OVER (PARTITION BY sent_id ORDER BY clause, class, pos) - 1 AS rank FROM cl)"


def _ranked(spark, d):
    """(sent_id, lang, pos, rank) of every token: the silver target order."""
    at = Window.partitionBy("sent_id").orderBy("pos")
    clause = F.coalesce(F.sum((F.col("tag") == "PUNCT").cast("int")).over(at.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    rank = F.element_at(F.create_map(*[F.lit(x) for kv in (preorder.CLASS_RANK | {"PUNCT": 4}).items() for x in kv]), F.col("tag"))
    rows = _silver(spark, d).select("sent_id", "doc_id", "lang", "pos", "tok", "tag", clause.alias("clause"), rank.alias("class"))
    return rows.withColumn("rank", F.row_number().over(Window.partitionBy("sent_id").orderBy("clause", "class", "pos")) - 1)


def _perms(spark, d):
    return _ranked(spark, d).groupBy("sent_id", "lang").agg(F.transform(F.array_sort(F.collect_list(F.struct("pos", "rank"))), lambda c: c["rank"]).alias("perm"))


@query("order_gold", f"WITH {ORDER} SELECT sent_id, string_agg(rank::VARCHAR, ' ' ORDER BY pos) AS perm FROM rk GROUP BY sent_id")
def order_gold(spark, d):
    return _perms(spark, d).select("sent_id", F.array_join(F.transform("perm", lambda x: x.cast("string")), " ").alias("perm"))


@query("order_inversions", f"WITH {ORDER} SELECT a.sent_id, count(*) AS inversions FROM rk a JOIN rk b ON a.sent_id = b.sent_id AND a.pos < b.pos AND a.rank > b.rank GROUP BY a.sent_id")
def order_inversions(spark, d):
    rows = _perms(spark, d).select("sent_id", metrics.inversions(F.col("perm")).cast("long").alias("inversions"))
    return rows.where("inversions > 0")


@query("cost_decisions", f"WITH {ORDER}, n AS (SELECT sent_id, count(*) AS n FROM rk GROUP BY 1), i AS (SELECT a.sent_id, count(*) AS inv FROM rk a JOIN rk b ON a.sent_id = b.sent_id AND a.pos < b.pos AND a.rank > b.rank GROUP BY 1) SELECT n.sent_id, n AS words, coalesce(inv, 0)::BIGINT AS swaps, (2 * n - 1 + 2 * coalesce(inv, 0)) / n::DOUBLE AS per_word FROM n LEFT JOIN i ON n.sent_id = i.sent_id")
def cost_decisions(spark, d):
    """Decisions a word that the preorderer takes for every sentence's target order: a swap for each inversion."""
    rows = _perms(spark, d).select("sent_id", F.size("perm").cast("long").alias("words"), metrics.inversions(F.col("perm")).cast("long").alias("swaps"))
    return rows.withColumn("per_word", cost.decisions("word", F.col("words"), F.col("swaps")))


@query("kendall_identity", f"WITH {ORDER}, n AS (SELECT sent_id, any_value(lang) AS lang, count(*) AS n FROM rk GROUP BY 1), i AS (SELECT a.sent_id, count(*) AS inv FROM rk a JOIN rk b ON a.sent_id = b.sent_id AND a.pos < b.pos AND a.rank > b.rank GROUP BY 1) SELECT lang, round(avg(CASE WHEN n > 1 THEN 1 - 2 * coalesce(inv, 0) / (n * (n - 1) / 2) ELSE 1 END), 6)::DOUBLE AS kendall FROM n LEFT JOIN i USING (sent_id) GROUP BY lang")
def kendall_identity(spark, d):
    return _perms(spark, d).groupBy("lang").agg(F.round(F.avg(metrics.kendall(F.col("perm"))), 6).alias("kendall"))


_STEP = "nx AS (SELECT sent_id, lang, pos, rank, lag(rank) OVER w AS before, count(*) OVER (PARTITION BY sent_id) AS n FROM rk WINDOW w AS (PARTITION BY sent_id ORDER BY pos)), f AS (SELECT sent_id, any_value(lang) AS lang, any_value(n) AS n, sum((rank = coalesce(before, -1) + 1)::INT) + max((pos = n - 1 AND rank = n - 1)::INT) AS kept, sum((before IS NOT NULL AND rank <> before + 1)::INT) AS breaks FROM nx GROUP BY sent_id)"


@query("frs_identity", f"WITH {ORDER}, {_STEP} SELECT lang, round(avg(100.0 * kept / (n + 1)), 6)::DOUBLE AS frs_pairs, round(avg(CASE WHEN n > 1 THEN 100.0 * (1 - breaks / (n - 1)) ELSE 100.0 END), 6)::DOUBLE AS frs_chunks FROM f GROUP BY lang")
def frs_identity(spark, d):
    """Both forms of the fuzzy reordering score for the untouched order."""
    p = F.col("perm")
    return _perms(spark, d).groupBy("lang").agg(F.round(F.avg(metrics.frs_pairs(p)), 6).alias("frs_pairs"), F.round(F.avg(metrics.frs_chunks(p)), 6).alias("frs_chunks"))


@query("order_exact", f"WITH {ORDER}, e AS (SELECT sent_id, any_value(lang) AS lang, bool_and(rank = pos) AS same FROM rk GROUP BY 1) SELECT lang, round(avg(same::INT), 9)::DOUBLE AS exact FROM e GROUP BY lang")
def order_exact(spark, d):
    """Share of sentences whose own order is the target order."""
    same = F.col("perm") == F.transform(F.sequence(F.lit(0), F.size("perm") - 1), lambda i: i)
    return _perms(spark, d).groupBy("lang").agg(F.round(F.avg(same.cast("double")), 9).alias("exact"))


@query("derivations")
def derivations(spark, d):
    """Lazy against eager derivations of every sentence's target order: actions, swaps, and the formula of their number."""

    def run(batches):
        for batch in batches:
            rows = []
            for p in batch["perm"]:
                p = list(p)
                for eager in (True, False):
                    a = preorder.derivation(p, eager)
                    rows.append((eager, len(p), len(a), a.count(preorder.SWAP)))
            yield pd.DataFrame(rows, columns=["eager", "words", "steps", "swaps"])

    made = _perms(spark, d).mapInPandas(run, "eager boolean, words long, steps long, swaps long")
    formula = 2 * F.col("words") - 1 + 2 * F.col("swaps")
    return made.groupBy("eager").agg(F.count(F.lit(1)).alias("sentences"), F.sum("words").alias("words"), F.sum("steps").alias("steps"), F.sum("swaps").alias("swaps"), F.sum((F.col("steps") != formula).cast("long")).alias("off_formula"))


def _order_samples(spark, d, sentences=150):
    """All sentences of two tokens or more with gold tags, predicted tags of a tagger trained on other documents, and target ranks.

    Learned from: bounded samples of sentences of up to 40 tokens.
    """
    sents, tr, dev, lex = _tag_samples(spark, d, 300)
    tagger = quantize.coded(postag.build(tr, dev, clusters=cluster_map(lex)))
    keep = ["sent_id", "doc_id", "lang", "part", "toks", "tags"]
    both = postag.predict(sents.where(F.size("toks") >= 2), tagger, keep, "pred_tags", {"rank": ("array<int>", preorder.silver_ranks)})
    both = materialise(both, "orders")
    pick = lambda part, n: [r.asDict() for r in splits.stratified(both.where((F.col("part") == part) & (F.size("toks") <= 40)), "lang", "sent_id", n).collect()]
    return both, tagger, pick("train", sentences), pick("dev", sentences // 5)


def _as_seen(rows: list[dict]) -> list[dict]:
    return [r | {"tags": r["pred_tags"]} for r in rows]


@query("preorder_trained")
def preorder_trained(spark, d):
    """Words alone, with predicted tags, with the tagger's inputs (in 8-bit codes); bracketing (of up to 40 tokens), rule order, identity and reverse, over sentences of any length.

    The KB of the model with predicted tags contain the tagger and its map.
    """
    both, tagger, tr, dev = _order_samples(spark, d)
    nets = {"words": preorder.build(tr, dev, "words"), "predicted tags": preorder.build(_as_seen(tr), _as_seen(dev), "tags"), "tagger inputs": preorder.build(tr, dev, "tagger_inputs")}
    nets = {n: quantize.coded(x) for n, x in nets.items()}
    nets["predicted tags"].resources["bytes"] = int(cost.size_kb(tagger) * 1024)
    kb = {n: round(cost.size_kb(x), 1) for n, x in nets.items()}
    got = preorder.evaluate(both.where("part = 'test'"), nets | {"bracketing": preorder.BracketPreorderer().fit(_as_seen(tr)), "rule": "rule", "identity": "identity", "reverse": "reverse"}, "pred_tags")
    return got.withColumn("kb", F.element_at(F.create_map(*[F.lit(x) for kv in kb.items() for x in kv]), F.col("model")))


@query("preorder_grid")
def preorder_grid(spark, d):
    """Grid search of the preorderer with predicted tags by the score of decoded held-out sentences."""
    _, _, tr, dev = _order_samples(spark, d, 60)
    net = preorder.start("tags")
    data = [preorder.gold_data(_as_seen(rows), net.template, "tags") for rows in (tr, dev)]
    return train.grid(spark, net, *data[0], data[1], train.Settings(epochs=1), _TRIALS, preorder.score_of(_as_seen(dev)))


# --- pipelines ---------------------------------------------------------------------


@query("pipeline_tag_preorder")
def pipeline_tag_preorder(spark, d):
    """Tagging and preordering of all test sentences in one pass: tokens a second and the tagger's share."""
    both, tagger, tr, dev = _order_samples(spark, d)
    net = quantize.coded(preorder.build(_as_seen(tr), _as_seen(dev), "tags"))
    return pipelines.stage_share(pipelines.tag_preorder(both.where("part = 'test'"), tagger, net, ["sent_id"]))


def _three_stages(spark, d):
    """A language model, and a segmenter and a tagger for each language, in 8-bit codes; sentences split for testing."""
    parts, tr, dev = _langid_samples(spark, d, 100)
    language = quantize.coded(langid.build(tr, dev, 8, hidden=64))
    words = materialise(splits.assign(_words(spark, d).where(F.size("words") > 0), "doc_id"), "seg-sentences")
    some = splits.stratified(words.where((F.col("part") == "train") & (F.size("words") <= 60)), "lang", "sent_id", 120).select("lang", "words").collect()
    _, tag_tr, tag_dev, lex = _tag_samples(spark, d, 200)
    held = cluster_map(lex)
    segmenters, taggers = {}, {}
    for lang in language.classes:
        mine = [r["words"] for r in some if r["lang"] == lang] or [r["words"] for r in some]
        net, enc = segment.build(mine, mine[:20], 32, bigrams=True)
        segmenters[lang] = (quantize.coded(net), enc)
        own = lambda rows, lang=lang: [r for r in rows if r["lang"] == lang] or rows
        taggers[lang] = quantize.coded(postag.build(own(tag_tr), own(tag_dev), 8, clusters=held, epochs=2))
    return language, segmenters, taggers, words.where("part = 'test'")


#: Layers and width of the recurrent baseline whose operations are compared.
LSTM_SHAPE = (4, 160)


@query("pipeline_lang_seg_tag")
def pipeline_lang_seg_tag(spark, d):
    """Language, words and tags of unsegmented sentences and of conversation turns in one pass, by models of the predicted language.

    How often the language is right, words, tags, and the operations a token beside those of a byte-level recurrent model.
    """
    language, segmenters, taggers, test = _three_stages(spark, d)
    joined = test.select(F.lit("documents").alias("tab"), "lang", F.array_join("words", "").alias("text"))
    talk = load(spark, d, "conversations").select(F.lit("conversations").alias("tab"), F.lit(None).cast("string").alias("lang"), F.regexp_replace(F.coalesce("text", F.lit("")), r"\s+", "").alias("text")).where("text <> ''")
    got = materialise(pipelines.lang_seg_tag(joined.unionByName(talk), language, segmenters, taggers, ["tab", "lang", "text"]), "three-stages")
    per = lambda nets: max(cost.net_flops(n) for n in nets)
    ours = F.sum(F.lit(float(cost.net_flops(language))) + per(s for s, _ in segmenters.values()) * F.length("text") + per(taggers.values()) * F.size("words"))
    theirs = F.sum(F.octet_length("text")) * float(cost.lstm_flops(*LSTM_SHAPE))
    tokens = F.sum(F.size("words"))
    return got.groupBy("tab", "lang").agg(F.count(F.lit(1)).alias("sentences"), F.avg((F.col("lang") == F.col("lang_pred")).cast("double")).alias("lang_right"), tokens.alias("words"), F.sum(F.size("tags")).alias("tags"), (ours / tokens).alias("flops_per_token"), (theirs / tokens).alias("lstm_flops_per_token"), (theirs / ours).alias("fewer_operations"))


# --- throughput (wall clock of warm scoring passes over whole tables) ---------------


def _timed(df: DataFrame) -> float:
    """Seconds of the second of two full passes whose rows are dropped."""
    import time

    for _ in range(2):
        began = time.time()
        df.write.format("noop").mode("overwrite").save()
    return time.time() - began


@query("langid_throughput")
def langid_throughput(spark, d):
    """Documents and megabytes a second of the sixteen-dimensional model over all documents, by strategy of decoding."""
    base = docs(spark, d)
    parts = langid.split_docs(base)
    net = langid.build(langid.sample(parts, "train", 40, 1), langid.sample(parts, "dev", 20, 2), 16, epochs=1)
    dealt = base.select("doc_id", "text").repartition(int(spark.conf.get("spark.sql.shuffle.partitions")))
    size = base.agg(F.count(F.lit(1)).alias("n"), F.sum(F.octet_length("text")).alias("b")).first()
    rows = []
    for name, n in (("float", net), ("8 bits, decoded as read", quantize.coded(net))):
        s = _timed(langid.score(dealt, n, "text", ["doc_id"]))
        rows.append((name, size["n"] / s, size["b"] / 1e6 / s))
    return spark.createDataFrame(rows, "model string, docs_per_second double, mb_per_second double")


@query("strategy_throughput")
def strategy_throughput(spark, d):
    """Documents and megabytes a second of the analytic model by each physical strategy."""
    base = docs(spark, d)
    size = base.agg(F.count(F.lit(1)).alias("n"), F.sum(F.octet_length("text")).alias("b")).first()
    dealt = materialise(base.select("doc_id", "text").repartition(int(spark.conf.get("spark.sql.shuffle.partitions"))), "dealt")
    rows = []
    for strategy in ("relational", "inrow", "vector"):
        s = _timed(forward.predict(dealt, MODEL, "doc_id", strategy=strategy))
        rows.append((strategy, size["n"] / s, size["b"] / 1e6 / s))
    return spark.createDataFrame(rows, "strategy string, docs_per_second double, mb_per_second double")


@query("tagger_throughput")
def tagger_throughput(spark, d):
    """Tokens a second of the half-size tagger with clusters from its map, in 8-bit codes, over all sentences."""
    sents, tr, dev, lex = _tag_samples(spark, d, 100)
    net = quantize.coded(postag.build(tr, dev, 8, clusters=cluster_map(lex), epochs=1))
    dealt = materialise(sents.select("sent_id", "toks").repartition(int(spark.conf.get("spark.sql.shuffle.partitions"))), "sentences")
    n = dealt.agg(F.sum(F.size("toks"))).first()[0]
    return spark.createDataFrame([(n / _timed(postag.predict(dealt, net, ["sent_id"])),)], "tokens_per_second double")


@query("segmenter_throughput")
def segmenter_throughput(spark, d):
    """Characters, kilobytes and words a second of the bigram segmenter in 8-bit codes over all sentences."""
    dealt = spread(docs(spark, d).select("doc_id", "lang", "text"), "doc_id")  # whole texts are dealt before they are cut
    words = materialise(_words(spark, d, dealt).where(F.size("words") > 0), "seg-sentences")
    some = [r["words"] for r in splits.stratified(words, "lang", "sent_id", 50).collect()]
    net, enc = segment.build(some, some[:20], 64, bigrams=True, epochs=1)
    n = words.agg(F.sum(F.length(F.array_join("words", ""))).alias("c"), F.sum(F.octet_length(F.array_join("words", ""))).alias("b"), F.sum(F.size("words")).alias("w")).first()
    s = _timed(segment.evaluate(words, _GreedyKernel(quantize.coded(net), enc)))
    return spark.createDataFrame([(n["c"] / s, n["b"] / 1000 / s, n["w"] / s)], "chars_per_second double, kb_per_second double, tokens_per_second double")
