"""Features, hashing, the network's layers, quantization, splits, measures and costs."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import hashing, text
from ..operators import cost, features, forward, metrics, quantize, splits
from ..operators.model import AnalyticModel
from ..registry import query
from ..sources.tables import load

MODEL = AnalyticModel()
BUCKET = "('0x' || substr(md5({x}), 1, 8))::BIGINT % {v}"


def docs(spark: SparkSession, d: str) -> DataFrame:
    return load(spark, d, "documents")


def sql_grams(orders=(1, 2, 3, 4), table="documents", key="doc_id", column="text") -> str:
    """CTEs ``c`` (code points) and ``grams`` (key, n, x), one row per n-gram occurrence."""
    parts = " UNION ALL ".join(f"SELECT {key}, {n} AS n, {' || '.join(f'list_extract(c, i + {k})' if k else 'list_extract(c, i)' for k in range(n))} AS x FROM (SELECT {key}, c, unnest(range(1, len(c) - {n - 2})) AS i FROM c)" for n in orders)
    return f"c AS (SELECT {key}, regexp_extract_all(lower(coalesce({column}, '')), '(?s).') AS c FROM {table}), grams AS ({parts})"


for _n in (1, 2, 3, 4):

    def _ngram(spark, d, n=_n):
        grams = docs(spark, d).select(F.explode(text.char_ngrams(F.col("text"), n)).alias("gram"))
        return grams.groupBy("gram").agg(F.count(F.lit(1)).alias("n"))

    query(f"ngram_counts_n{_n}", f"WITH {sql_grams((_n,))} SELECT x AS gram, count(*) AS n FROM grams GROUP BY x")(_ngram)

for _v in (100, 500, 1000, 5000):

    def _buckets(spark, d, v=_v):
        grams = docs(spark, d).select(F.explode(text.char_ngrams(F.col("text"), 3)).alias("gram"))
        return grams.groupBy(hashing.bucket(F.col("gram"), v, "md5").cast("long").alias("v")).agg(F.count(F.lit(1)).alias("n"))

    query(f"hash_buckets_v{_v}", f"WITH {sql_grams((3,))} SELECT {BUCKET.format(x='x', v=_v)} AS v, count(*) AS n FROM grams GROUP BY 1")(_buckets)


_AUDIT = " UNION ALL ".join(
    f"SELECT {v}::BIGINT AS buckets, sum(n)::BIGINT AS values, count(*) AS used, max(n) AS fullest, (sum(n) - count(*))::BIGINT AS collisions, round(sum(n * n) / (sum(n) / {v}::DOUBLE) - sum(n), 6)::DOUBLE AS chi_square FROM (SELECT {BUCKET.format(x='x', v=v)} AS v, count(*) AS n FROM u GROUP BY 1)"
    for v in (100, 500, 1000, 5000)
)


@query("hash_audit", f"WITH {sql_grams((3,))}, u AS (SELECT DISTINCT x FROM grams) {_AUDIT}")
def hash_audit(spark, d):
    grams = docs(spark, d).select(F.explode(text.char_ngrams(F.col("text"), 3)).alias("gram")).distinct()
    out = hashing.audit(grams, "gram", 100)
    for v in (500, 1000, 5000):
        out = out.unionByName(hashing.audit(grams, "gram", v))
    return out


@query("hash_algorithms")
def hash_algorithms(spark, d):
    """Spread of the three hashes over 1,000 buckets."""
    grams = docs(spark, d).select(F.explode(text.char_ngrams(F.col("text"), 3)).alias("gram")).distinct()
    parts = [hashing.audit(grams, "gram", 1000, a).withColumn("algo", F.lit(a)) for a in ("xxhash64", "md5", "crc32")]
    return parts[0].unionByName(parts[1]).unionByName(parts[2])


@query(
    "vocab_with_unknown",
    """WITH t AS (SELECT unnest(regexp_extract_all(lower(coalesce(text, '')), '[^ \\t\\n]+')) AS w FROM documents),
    f AS (SELECT w, count(*) AS freq FROM t GROUP BY w)
    SELECT w AS value, freq, row_number() OVER (ORDER BY freq DESC, w) AS id FROM f WHERE freq >= 2
    UNION ALL SELECT '<unknown>', coalesce(sum(freq), 0)::BIGINT, 0 FROM f WHERE freq < 2""",
)
def vocab_with_unknown(spark, d):
    words = docs(spark, d).select(F.explode(F.regexp_extract_all(F.lower("text"), F.lit(r"[^ \t\n]+"), F.lit(0))).alias("w"))
    vocab = features.build_vocab(words, "w")
    total = words.agg(F.count(F.lit(1)).alias("all"))
    known = vocab.agg(F.coalesce(F.sum("freq"), F.lit(0)).alias("known"))
    unknown = total.crossJoin(known).select(F.lit("<unknown>").alias("value"), (F.col("all") - F.col("known")).alias("freq"), F.lit(0).cast("long").alias("id"))  # two single rows
    return vocab.select("value", "freq", "id").unionByName(unknown)


def _emb_sql() -> str:
    cells = ", ".join(f"((v * {31 + 7 * e} + 17 * grp + {5 * e * e}) % 15 - 7) * cnt AS w{e}" for e in range(MODEL.dim))
    case = " ".join(f"WHEN {n} THEN {BUCKET.format(x='x', v=v)}" for n, v in zip(MODEL.orders, MODEL.vocab, strict=True))
    return f"""WITH {sql_grams(MODEL.orders)},
    b AS (SELECT doc_id, (n - 1)::BIGINT AS grp, CASE n {case} END AS v FROM grams),
    k AS (SELECT doc_id, grp, v, count(*) AS cnt FROM b GROUP BY ALL),
    w AS (SELECT doc_id, grp, cnt, {cells} FROM k),
    s AS (SELECT doc_id, grp, sum(cnt)::BIGINT AS total, {', '.join(f'sum(w{e})::BIGINT AS s{e}' for e in range(MODEL.dim))} FROM w GROUP BY ALL)"""


EMB = _emb_sql()
_MEAN = ", ".join(f"floor(128.0::DOUBLE * s{e} / total)::BIGINT AS e{e}" for e in range(MODEL.dim))


def _embedded(spark, d, combine="mean"):
    return forward.combined(forward.group_sums(docs(spark, d), "doc_id", "text", MODEL), "doc_id", MODEL, combine)


@query("embed_mean", f"{EMB} SELECT doc_id, grp, {_MEAN} FROM s")
def embed_mean(spark, d):
    return _embedded(spark, d).withColumn("grp", F.col("grp").cast("long"))


@query("embed_sum", f"{EMB} SELECT doc_id, grp, {', '.join(f's{e} AS e{e}' for e in range(MODEL.dim))} FROM s")
def embed_sum(spark, d):
    return _embedded(spark, d, "sum").withColumn("grp", F.col("grp").cast("long"))


def _h0_sql() -> str:
    cells = ", ".join(f"coalesce(max(e{e}) FILTER (grp = {g}), 0) AS x{g * MODEL.dim + e}" for g in range(len(MODEL.orders)) for e in range(MODEL.dim))
    names = [f"x{i}" for i in range(MODEL.h0)]
    return f"{EMB}, m AS (SELECT doc_id, grp, {_MEAN} FROM s), h AS (SELECT doc_id, {cells} FROM m GROUP BY doc_id), h0 AS (SELECT documents.doc_id, {', '.join(f'coalesce({x}, 0) AS {x}' for x in names)} FROM documents LEFT JOIN h USING (doc_id))"


def _sum_sql(weights, prefix) -> str:
    return " + ".join(f"({w}) * {prefix}{i}" for i, w in enumerate(weights))


H0 = _h0_sql()
H1 = H0 + ", h1 AS (SELECT doc_id, " + ", ".join(f"greatest(0, {_sum_sql([MODEL.hidden_weight(j, i) for i in range(MODEL.h0)], 'x')} + {MODEL.hidden_bias(j) * 16})::BIGINT AS a{j}" for j in range(MODEL.hidden)) + " FROM h0)"
Z = H1 + ", z AS (SELECT doc_id, " + ", ".join(f"({_sum_sql([MODEL.output_weight(y, j) for j in range(MODEL.hidden)], 'a')})::BIGINT AS z{y}" for y in range(len(MODEL.classes))) + " FROM h1)"
_BEST = "greatest(" + ", ".join(f"z{y}" for y in range(len(MODEL.classes))) + ")"
LABEL = Z + ", lab AS (SELECT doc_id, CASE " + " ".join(f"WHEN z{y} = {_BEST} THEN '{c}'" for y, c in enumerate(MODEL.classes)) + f" END AS label, {_BEST} AS score FROM z)"


def _h0(spark, d):
    rows = docs(spark, d).select("doc_id", "text")
    return forward.concat_groups(_embedded(spark, d), rows, "doc_id", MODEL)


@query("embed_concat", f"{H0} SELECT * FROM h0")
def embed_concat(spark, d):
    return _h0(spark, d).select("doc_id", *[F.col("h0")[i].alias(f"x{i}") for i in range(MODEL.h0)])


@query("hidden_layer", f"{H1} SELECT * FROM h1")
def hidden_layer(spark, d):
    h1 = _h0(spark, d).select("doc_id", forward.hidden(F.col("h0"), MODEL).alias("h1"))
    return h1.select("doc_id", *[F.col("h1")[j].alias(f"a{j}") for j in range(MODEL.hidden)])


def _z(spark, d):
    return _h0(spark, d).select("doc_id", forward.hidden(F.col("h0"), MODEL).alias("h1")).select("doc_id", forward.logits(F.col("h1"), MODEL).alias("z"))


@query("langid_logits", f"{Z} SELECT * FROM z")
def langid_logits(spark, d):
    return _z(spark, d).select("doc_id", *[F.col("z")[y].alias(f"z{y}") for y in range(len(MODEL.classes))])


_EXP = [f"exp((z{y} - {_BEST})::DOUBLE / 100000.0::DOUBLE)" for y in range(len(MODEL.classes))]


@query("softmax", f"{Z} SELECT doc_id, " + ", ".join(f"round({e} / ({' + '.join(_EXP)}), 6)::DOUBLE AS p{y}" for y, e in enumerate(_EXP)) + " FROM z")
def softmax(spark, d):
    p = forward.probabilities(F.col("z"), 100000.0)
    return _z(spark, d).select("doc_id", p.alias("p")).select("doc_id", *[F.round(F.col("p")[y], 6).alias(f"p{y}") for y in range(len(MODEL.classes))])


for _strategy in ("relational", "inrow", "vector"):
    query(f"langid_label_{_strategy}", f"{LABEL} SELECT doc_id, label, score FROM lab")(lambda spark, d, s=_strategy: forward.predict(docs(spark, d), MODEL, "doc_id", strategy=s))


@query("analytic_language_counts", f"{LABEL} SELECT label, count(*) AS n FROM lab GROUP BY label")
def analytic_language_counts(spark, d):
    return forward.predict(docs(spark, d), MODEL, "doc_id").groupBy("label").agg(F.count(F.lit(1)).alias("n"))


def _judged(spark, d):
    return docs(spark, d).select("doc_id", "lang").join(forward.predict(docs(spark, d), MODEL, "doc_id"), "doc_id")


_J = f"{LABEL}, j AS (SELECT lang AS gold, label AS pred FROM lab JOIN documents USING (doc_id))"
_PER = ", l AS (SELECT DISTINCT gold AS label FROM j UNION SELECT DISTINCT pred FROM j), pc AS (SELECT label, (SELECT count(*) FROM j WHERE gold = label AND pred = label) AS tp, (SELECT count(*) FROM j WHERE pred = label AND gold <> label) AS fp, (SELECT count(*) FROM j WHERE gold = label AND pred <> label) AS fn FROM l), f AS (SELECT *, CASE WHEN tp + fp > 0 THEN tp / (tp + fp) ELSE 0 END::DOUBLE AS precision, CASE WHEN tp + fn > 0 THEN tp / (tp + fn) ELSE 0 END::DOUBLE AS recall, (2 * tp / (2 * tp + fp + fn))::DOUBLE AS f1 FROM pc)"


@query("micro_f1", f"{_J} SELECT avg((gold = pred)::INT)::DOUBLE AS micro_f1 FROM j")
def micro_f1(spark, d):
    return metrics.micro_f1(_judged(spark, d), "lang", "label")


@query("macro_f1", f"{_J}{_PER} SELECT round(avg(f1), 9) AS macro_f1 FROM f")
def macro_f1(spark, d):
    return metrics.macro_f1(_judged(spark, d), "lang", "label").select(F.round("macro_f1", 9).alias("macro_f1"))


@query("per_class", f"{_J}{_PER} SELECT label, tp, fp, fn, precision, recall, f1 FROM f")
def per_class(spark, d):
    return metrics.per_class(_judged(spark, d), "lang", "label")


@query("confusion", f"{_J} SELECT gold, pred, count(*) AS n FROM j GROUP BY ALL")
def confusion(spark, d):
    return metrics.confusion(_judged(spark, d), "lang", "label")


def _vectors(spark, d):
    return load(spark, d, "embeddings").select("vec_id", "label", F.col("embedding").alias("w"))


for _bits in (4, 8):
    _L = quantize.limit(_bits)
    _S = f"(list_max(list_transform(embedding, lambda x: abs(x::DOUBLE))) / {_L})"
    _Q = f"e AS (SELECT vec_id, label, embedding, {_S} AS scale FROM embeddings), q AS (SELECT vec_id, label, embedding, scale, list_transform(embedding, lambda x: CASE WHEN scale = 0 THEN 0 ELSE round(x::DOUBLE / scale) END) AS codes FROM e)"

    def _codes(spark, d, bits=_bits):
        q = quantize.encode(_vectors(spark, d), bits=bits)
        return q.select("vec_id", F.round("scale", 9).alias("scale"), F.array_join(F.transform("codes", lambda x: x.cast("string")), ",").alias("codes"))

    def _back(spark, d, bits=_bits):
        q = quantize.decode(quantize.encode(_vectors(spark, d), bits=bits))
        return q.select("vec_id", F.round(F.aggregate("restored", F.lit(0.0), lambda a, x: a + F.abs(x)), 6).alias("l1"), F.round(F.array_max("restored"), 6).alias("top"))

    def _err(spark, d, bits=_bits):
        return quantize.error(quantize.encode(_vectors(spark, d), bits=bits), by="label")

    query(f"quant_codes_{_bits}", f"WITH {_Q} SELECT vec_id, round(scale, 9)::DOUBLE AS scale, array_to_string(list_transform(codes, lambda x: x::BIGINT), ',') AS codes FROM q")(_codes)
    query(f"quant_roundtrip_{_bits}", f"WITH {_Q} SELECT vec_id, round(list_sum(list_transform(codes, lambda x: abs(x * scale))), 6) AS l1, round(list_max(list_transform(codes, lambda x: x * scale)), 6) AS top FROM q")(_back)
    query(
        f"quant_error_{_bits}",
        f"WITH {_Q}, d AS (SELECT label, scale, list_transform(list_zip(embedding, codes), lambda p: abs(p[1]::DOUBLE - p[2] * scale)) AS err FROM q) SELECT label, round(max(list_max(err)), 6) AS max_error, round(sum(list_sum(err)) / sum(len(err)), 6) AS mean_error, round(max(list_max(err) / scale) FILTER (scale > 0), 6) AS max_in_scales FROM d GROUP BY label",
    )(_err)


_GROUP = "[(list_max(list_transform(embedding[j * 16 + 1 : j * 16 + 16], lambda x: abs(x::DOUBLE))) / 127) for j in range(0, 4)]"


@query(
    "quant_error_group",
    f"WITH e AS (SELECT label, embedding, {_GROUP} AS s FROM embeddings), q AS (SELECT label, [abs(embedding[i]::DOUBLE - CASE WHEN s[(i - 1) // 16 + 1] = 0 THEN 0 ELSE round(embedding[i]::DOUBLE / s[(i - 1) // 16 + 1]) * s[(i - 1) // 16 + 1] END) for i in range(1, 65)] AS err FROM e) SELECT label, round(max(list_max(err)), 6) AS max_error, round(sum(list_sum(err)) / sum(len(err)), 6) AS mean_error FROM q GROUP BY label",
)
def quant_error_group(spark, d):
    """Errors of 8-bit codes with a scale for every 16 numbers of a row."""
    q = quantize.decode(quantize.encode(_vectors(spark, d), bits=8, scale="group"))
    err = F.zip_with("w", "restored", lambda a, b: F.abs(a.cast("double") - b))
    rows = q.select("label", F.array_max(err).alias("most"), F.aggregate(err, F.lit(0.0), lambda a, x: a + x).alias("total"), F.size(err).alias("n"))
    return rows.groupBy("label").agg(F.round(F.max("most"), 6).alias("max_error"), F.round(F.sum("total") / F.sum("n"), 6).alias("mean_error"))


@query(
    "quant_error_matrix",
    "WITH m AS (SELECT max(list_max(list_transform(embedding, lambda x: abs(x::DOUBLE)))) / 127 AS s FROM embeddings), q AS (SELECT label, list_transform(embedding, lambda x: abs(x::DOUBLE - round(x::DOUBLE / s) * s)) AS err FROM embeddings, m) SELECT label, round(max(list_max(err)), 6) AS max_error, round(sum(list_sum(err)) / sum(len(err)), 6) AS mean_error FROM q GROUP BY label",
)
def quant_error_matrix(spark, d):
    """Errors of 8-bit codes with one scale for the whole matrix."""
    return quantize.error(quantize.encode(_vectors(spark, d), bits=8, scale="matrix"), by="label").drop("max_in_scales")


@query("quant_budget_sweep", "SELECT dims::BIGINT AS dims, bits::BIGINT AS bits, (11000 * dims * bits / 8 + 11000 * CASE WHEN bits = 32 THEN 0 ELSE 2 END + 4 * (4 * dims * 208 + 208 + 208 * 66 + 66)) / 1024.0::DOUBLE AS kb FROM (VALUES (6), (8), (12), (16), (24), (32)) d(dims), (VALUES (32), (16), (8), (4), (2)) b(bits)")
def quant_budget_sweep(spark, d):
    """Size of the language-id shape for dimensions against bits: where equal budgets lie."""
    grid = spark.createDataFrame([(x, b) for x in (6, 8, 12, 16, 24, 32) for b in (32, 16, 8, 4, 2)], "dims long, bits long")
    scale = F.when(F.col("bits") == 32, 0).otherwise(2)
    dense = 4 * (4 * F.col("dims") * 208 + 208 + 208 * 66 + 66)
    return grid.select("dims", "bits", ((11000 * F.col("dims") * F.col("bits") / 8 + 11000 * scale + dense) / 1024.0).alias("kb"))


_P = "(('0x' || substr(md5(doc_id::VARCHAR), 1, 8))::BIGINT % 100)"
_PART = f"CASE WHEN {_P} < 80 THEN 'train' WHEN {_P} < 90 THEN 'dev' ELSE 'test' END"


@query("split_assign", f"SELECT doc_id, {_PART} AS part FROM documents")
def split_assign(spark, d):
    return splits.assign(docs(spark, d), "doc_id").select("doc_id", "part")


@query("twins_dropped", f"WITH p AS (SELECT doc_id, text, {_PART} AS part FROM documents) SELECT doc_id, part FROM p WHERE part = 'train' OR text NOT IN (SELECT text FROM p WHERE part = 'train')")
def twins_dropped(spark, d):
    return splits.drop_twins(splits.assign(docs(spark, d), "doc_id").select("doc_id", "part", "text")).select("doc_id", "part")


@query("stratified_sample", "SELECT doc_id, lang FROM documents QUALIFY row_number() OVER (PARTITION BY lang ORDER BY md5(doc_id::VARCHAR), doc_id) <= 50")
def stratified_sample(spark, d):
    return splits.stratified(docs(spark, d).select("doc_id", "lang"), "lang", "doc_id", 50)


@query("lr_schedule", "SELECT step, 0.1::DOUBLE * power(0.96::DOUBLE, step / 1000.0::DOUBLE) AS rate FROM (SELECT unnest(range(0, 20001, 500)) AS step)")
def lr_schedule(spark, d):
    return spark.range(0, 20001, 500).select(F.col("id").alias("step"), (F.lit(0.1) * F.pow(F.lit(0.96), F.col("id") / 1000.0)).alias("rate"))


#: The dense layers of the language-id shape for ``dim`` numbers a group: 208 hidden units, 66 classes.
_DENSE = "(4 * dim * 208 + 208 + 208 * 66 + 66)"
_ROWS = "t AS (SELECT label, len(embedding)::BIGINT AS dim, count(*) AS n FROM embeddings GROUP BY 1, 2)"


def _embedding_rows(spark, d):
    """(label, dim, n): the given vectors as one embedding matrix a label."""
    return load(spark, d, "embeddings").groupBy("label", F.size("embedding").cast("long").alias("dim")).agg(F.count(F.lit(1)).alias("n"))


def _dense_params(dim):
    return cost.dense_params(4 * dim, 208, 66)


@query("cost_params", f"WITH {_ROWS} SELECT label, dim, n, (n * dim + {_DENSE})::BIGINT AS params FROM t")
def cost_params(spark, d):
    """Parameters of the language-id shape whose embedding rows are the given vectors of a label."""
    dim = F.col("dim")
    return _embedding_rows(spark, d).select("label", "dim", "n", (F.col("n") * dim + _dense_params(dim)).alias("params"))


@query("cost_size_kb", f"WITH {_ROWS} SELECT label, dim, bits::BIGINT AS bits, round((n * dim * bits / 8 + n * scale + 4 * {_DENSE}) / 1024.0, 4)::DOUBLE AS kb FROM t, (VALUES (32, 0), (8, 2)) b(bits, scale)")
def cost_size_kb(spark, d):
    """Kilobytes of the same networks, with exact embeddings and in 8-bit codes with a scale of two bytes a row."""
    dim, n = F.col("dim"), F.col("n")
    kb = lambda bits, scale: F.struct(F.lit(bits).cast("long").alias("bits"), F.round((n * dim * bits / 8 + n * scale + 4 * _dense_params(dim)) / 1024, 4).alias("kb"))
    return _embedding_rows(spark, d).select("label", "dim", F.inline(F.array(kb(32, 0), kb(8, 2))))


_GRAMS = " + ".join(f"greatest(length(text) - {n - 1}, 0)" for n in (1, 2, 3, 4))


@query("cost_flops", f"SELECT lang, h0::BIGINT AS h0, hidden::BIGINT AS hidden, classes::BIGINT AS classes, docs, (grams * h0 // 4)::BIGINT AS adds, (docs * (2 * h0 * hidden + 2 * hidden * classes))::BIGINT AS flops, (docs * (2 * h0 * hidden + 2 * hidden * classes + hidden + classes))::BIGINT AS flops_bias FROM (SELECT lang, count(*) AS docs, coalesce(sum({_GRAMS}), 0)::BIGINT AS grams FROM documents GROUP BY lang) t, (VALUES (24, 208, 66), (64, 208, 66), (64, 208, 4), (160, 64, 10)) s(h0, hidden, classes)")
def cost_flops(spark, d):
    """Operations of scoring all documents of a language by four shapes: additions that average n-grams, and the passes given h0."""
    long = lambda x: F.lit(x).cast("long")
    grams = sum(F.greatest(F.length("text") - (n - 1), F.lit(0)).cast("long") for n in (1, 2, 3, 4))
    of = docs(spark, d).groupBy("lang").agg(F.count(F.lit(1)).alias("docs"), F.coalesce(F.sum(grams), F.lit(0)).alias("grams"))
    shape = lambda h, m, c: F.struct(long(h).alias("h0"), long(m).alias("hidden"), long(c).alias("classes"), F.col("docs"), (F.col("grams") * (h // 4)).alias("adds"), (F.col("docs") * cost.flops(h, m, c)).alias("flops"), (F.col("docs") * cost.flops(h, m, c, count_bias=True)).alias("flops_bias"))
    return of.select("lang", F.inline(F.array(*[shape(*s) for s in ((24, 208, 66), (64, 208, 66), (64, 208, 4), (160, 64, 10))])))


@query("cost_lstm", "SELECT lang, layers::BIGINT AS layers, width::BIGINT AS width, steps, (layers * 4 * width * (2 * width + 1))::BIGINT AS params, (steps * layers * 8 * width * 2 * width)::BIGINT AS flops FROM (SELECT lang, coalesce(sum(octet_length(encode(text))), 0)::BIGINT AS steps FROM documents GROUP BY lang) t, (VALUES (4, 160), (4, 320), (2, 160)) s(layers, width)")
def cost_lstm(spark, d):
    """A recurrent network over the bytes of all documents of a language: a step a byte."""
    long = lambda x: F.lit(x).cast("long")
    of = docs(spark, d).groupBy("lang").agg(F.coalesce(F.sum(F.octet_length("text").cast("long")), F.lit(0)).alias("steps"))
    shape = lambda n, w: F.struct(long(n).alias("layers"), long(w).alias("width"), F.col("steps"), long(cost.lstm_params(n, w)).alias("params"), cost.lstm_flops(n, w, F.col("steps")).alias("flops"))
    return of.select("lang", F.inline(F.array(*[shape(*s) for s in ((4, 160), (4, 320), (2, 160))])))


#: Published values, used for the derived ratios only.
PUBLISHED = {"tagger_vanilla": (94.76, 241_000, 0.27e6), "tagger_clusters": (95.56, 261_000, 0.31e6), "tagger_half": (95.39, 143_000, 0.18e6), "byte_span_lstm": (95.06, 900_000, 6.63e6)}


@query(
    "paper_ratios",
    "SELECT name, round(value, 6)::DOUBLE AS value FROM (VALUES ('error reduction, clusters', (95.56 - 94.76) / (100 - 94.76)), ('error reduction, half dims', (95.39 - 94.76) / (100 - 94.76)), ('fewer parameters', 900000 / 143000.0), ('fewer operations', 6.63 / 0.18), ('map bits per key', 300 * 1024 * 8 / 250000.0), ('pipeline operations, millions', 6.63 / 12)) t(name, value)",
)
def paper_ratios(spark, d):
    v, c, h, b = (PUBLISHED[k] for k in ("tagger_vanilla", "tagger_clusters", "tagger_half", "byte_span_lstm"))
    rows = [("error reduction, clusters", metrics.rel_error_reduction(v[0], c[0])), ("error reduction, half dims", metrics.rel_error_reduction(v[0], h[0])), ("fewer parameters", b[1] / h[1]), ("fewer operations", b[2] / h[2]), ("map bits per key", 300 * 1024 * 8 / 250_000), ("pipeline operations, millions", b[2] / 1e6 / 12)]
    return spark.createDataFrame([(n, round(x, 6)) for n, x in rows], "name string, value double")
