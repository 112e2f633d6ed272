"""The thin contract queries of the operators, with their SQL where SQL can express them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.scratch import materialise
from . import decontaminate, exact_dedup, jaccard, language, licenses, mixing, quality, secrets, toxicity, warc
from .rows import fold_of


def _read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _held_out(scored: DataFrame, *cols: str) -> DataFrame:
    return scored.select("doc_id", (fold_of(F.col("doc_id")) == 0).alias("held_out"), *cols)


def op1_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _read(spark, sf_dir, "documents")
    model = toxicity.fit(docs, toxicity.train_labels(_read(spark, sf_dir, "labels")))
    return _held_out(toxicity.score(docs, model, keep=["doc_id"]), "score", "predicted")


def op2_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _read(spark, sf_dir, "documents")
    model = quality.fit(docs, toxicity.train_labels(_read(spark, sf_dir, "labels"), "quality"))
    return _held_out(quality.score(docs, model, keep=["doc_id"]), "score", "predicted")


def op3_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(_read(spark, sf_dir, "documents"))


def op4_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secrets.scan(_read(spark, sf_dir, "documents"))


def op5_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = decontaminate.contamination(_read(spark, sf_dir, "documents"), _read(spark, sf_dir, "benchmark"))
    return found.select("doc_id", "n_words", "n_hit", F.size("items").cast("long").alias("n_items"), decontaminate.item_digest(F.col("items")).alias("items_sha256"), "contaminated")


def op6_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _read(spark, sf_dir, "documents")
    learn = docs.where(fold_of(F.col("doc_id")) != 0)
    model = language.fit(learn, learn)
    return _held_out(language.score(docs, model, keep=["doc_id"]), "lang_pred", "score")


def op7_ngram_jaccard(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard.similarity_classes(_read(spark, sf_dir, "documents"))


def op8_licenses(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents as a file tree: every 500th id is its source's licence file, every 100th that of a folder of 1,000 ids."""
    i, top = F.col("doc_id"), F.concat(F.lit("/"), F.coalesce("source", F.lit("none")))
    folder = F.concat_ws("/", top, F.floor(i / 1000).cast("string"))
    path = F.when(i % 500 == 0, F.concat(top, F.lit("/LICENSE."), i.cast("string"))).when(i % 100 == 0, F.concat(folder, F.lit("/LICENSE."), i.cast("string"))).otherwise(F.concat(folder, F.lit("/"), i.cast("string"), F.lit(".txt")))
    files = licenses.detect(_read(spark, sf_dir, "documents").withColumn("path", path), keep=["doc_id", "path"])
    return licenses.inherit(materialise(files, "license-files")).select("doc_id", "path", "own_license", "own_score", "license", "inherited_from")


def op9_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup.exact_dedup(_read(spark, sf_dir, "documents"))


def op10_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    return warc.round_trip(_read(spark, sf_dir, "pages"))


def queries() -> dict:
    return {f.__name__: f for f in (op1_toxicity, op2_quality, op3_mix_sources, op4_secret_scan, op5_decontaminate, op6_language, op7_ngram_jaccard, op8_licenses, op9_exact_dedup, op10_warc)}


_OP3 = r"""
WITH d AS (
  SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+'))::BIGINT AS size,
         ('0x' || substr(md5(coalesce(doc_id::VARCHAR, '')), 1, 15))::BIGINT AS h
  FROM documents),
s AS (
  SELECT source, sum(size)::BIGINT AS source_size, row_number() OVER (ORDER BY source ASC NULLS LAST) AS place
  FROM d GROUP BY source),
w AS (SELECT *, [3, 1, 2][((place - 1) % 3 + 1)::INT] AS weight, 2.0::DOUBLE * source_size AS cap FROM s),
r AS (
  SELECT *, cap / weight AS rate,
         sum(cap) OVER (ORDER BY cap / weight, place ROWS UNBOUNDED PRECEDING) - cap AS capped,
         sum(weight) OVER (ORDER BY cap / weight, place ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS open_weight,
         (sum(source_size) OVER ())::DOUBLE * 1.5::DOUBLE AS budget
  FROM w),
f AS (SELECT (budget - capped) / open_weight AS open_rate FROM r WHERE (budget - capped) / open_weight <= rate ORDER BY rate, place LIMIT 1),
t AS (SELECT source, source_size, coalesce(least(cap, weight * (SELECT open_rate FROM f)), cap)::DOUBLE AS target FROM r),
p AS (
  SELECT *, CASE WHEN source_size > 0 THEN floor(target / source_size)::BIGINT ELSE 0 END AS passes FROM t),
g AS (
  SELECT source, h, sum(size) AS words, sum(sum(size)) OVER (PARTITION BY source ORDER BY h) AS upto FROM d GROUP BY source, h)
SELECT d.doc_id, d.size, p.source_size, p.target,
       CAST(d.size * (p.passes + CASE WHEN p.target - p.passes * p.source_size > 0
         AND (g.upto <= p.target - p.passes * p.source_size
              OR 2 * (p.target - p.passes * p.source_size - (g.upto - g.words)) >= g.words) THEN 1 ELSE 0 END) AS BIGINT) AS taken,
       CASE WHEN d.size > 0 THEN CAST(p.passes + CASE WHEN p.target - p.passes * p.source_size > 0
         AND (g.upto <= p.target - p.passes * p.source_size
              OR 2 * (p.target - p.passes * p.source_size - (g.upto - g.words)) >= g.words) THEN 1 ELSE 0 END AS BIGINT) ELSE 0 END AS copies
FROM d JOIN p ON d.source IS NOT DISTINCT FROM p.source
JOIN g ON d.source IS NOT DISTINCT FROM g.source AND d.h = g.h
"""

_OP4 = r"""
WITH kinds AS (
  SELECT * FROM (VALUES
    ('assign', 0, '((?:[pP][aA][sS][sS][wW][oO][rR][dD]|[pP][aA][sS][sS][wW][dD]|[sS][eE][cC][rR][eE][tT]|[tT][oO][kK][eE][nN]|[aA][pP][iI]_?[kK][eE][yY])["'']?\x20*[:=]\x20*["'']?)([A-Za-z0-9+/_.=-]+)', 8),
    ('access', 1, '(AKIA)([A-Z0-9]+)', 12),
    ('hex', 2, '()([0-9a-f]+)', 32),
    ('pem', 3, '()(-----BEGIN [A-Z ]{0,40}PRIVATE KEY-----)', 0)) AS k(kind, rank, pattern, least)),
m AS (
  SELECT doc_id, kind, rank, least, regexp_extract_all(text, pattern, 0) AS whole, regexp_extract_all(text, pattern, 2) AS own,
         string_split_regex(text, pattern) AS gaps
  FROM documents, kinds WHERE text IS NOT NULL),
x AS (
  SELECT doc_id, kind, rank, least, unnest(range(1, len(whole) + 1)) AS i, unnest(whole) AS w, unnest(own) AS o, unnest(gaps[1:len(whole)]) AS g FROM m),
e AS (
  SELECT doc_id, kind, rank, least, length(o) AS own, length(w) AS n, (sum(length(g) + length(w)) OVER (PARTITION BY doc_id, kind ORDER BY i))::BIGINT AS stop FROM x),
f AS (SELECT doc_id, kind, rank, stop - n AS start, kind || ':' || (stop - n) || ':' || stop AS span FROM e WHERE own >= least),
a AS (
  SELECT doc_id, count(*) FILTER (kind = 'assign') AS n_assign, count(*) FILTER (kind = 'access') AS n_access, count(*) FILTER (kind = 'hex') AS n_hex,
         string_agg(span, ',' ORDER BY start, rank) FILTER (kind <> 'pem') AS base, string_agg(span, ',' ORDER BY start, rank) AS spans
  FROM f GROUP BY doc_id)
SELECT doc_id, coalesce(n_assign, 0) AS n_assign, coalesce(n_access, 0) AS n_access, coalesce(n_hex, 0) AS n_hex,
       sha256(coalesce(base, '')) AS base_sha256, coalesce(spans, '') AS spans
FROM documents LEFT JOIN a USING (doc_id)
"""

_OP5 = r"""
WITH dw AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents),
iw AS (SELECT item_id::VARCHAR AS item, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM benchmark),
il AS (SELECT item, w, least(13, len(w)) AS k FROM iw WHERE len(w) > 0),
win AS (SELECT DISTINCT item, k, array_to_string(w[s:s + k - 1], ' ') AS t FROM (SELECT item, w, k, unnest(range(1, len(w) - k + 2)) AS s FROM il)),
ks AS (SELECT DISTINCT k FROM win),
pos AS (SELECT doc_id, k, s, array_to_string(w[s:s + k - 1], ' ') AS t FROM (SELECT doc_id, w, k, unnest(range(1, len(w) - k + 2)) AS s FROM dw, ks WHERE len(w) >= k)),
hit AS (SELECT doc_id, item, pos.k, s FROM pos JOIN win ON pos.k = win.k AND pos.t = win.t),
cov AS (SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(range(s, s + k)) AS p FROM hit) GROUP BY doc_id),
its AS (SELECT doc_id, count(*) AS n_items, string_agg(item, ',' ORDER BY item) AS items FROM (SELECT DISTINCT doc_id, item FROM hit) GROUP BY doc_id)
SELECT dw.doc_id, len(dw.w)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(n_items, 0)::BIGINT AS n_items, sha256(coalesce(items, '')) AS items_sha256,
       coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= len(dw.w) AS contaminated
FROM dw LEFT JOIN cov USING (doc_id) LEFT JOIN its USING (doc_id)
"""

_OP7 = r"""
WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents),
g AS (SELECT DISTINCT doc_id, array_to_string(w[s:s + 3], ' ') AS t FROM (SELECT doc_id, w, unnest(range(1, greatest(len(w) - 3, least(len(w), 1)) + 1)) AS s FROM w)),
n AS (SELECT doc_id, count(*) AS n FROM g GROUP BY doc_id),
p AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS i FROM g a JOIN g b ON a.t = b.t AND a.doc_id < b.doc_id GROUP BY 1, 2),
l AS (SELECT a, b FROM p JOIN n x ON a = x.doc_id JOIN n y ON b = y.doc_id WHERE 100 * i >= 85 * (x.n + y.n - i)),
e AS (SELECT a, b FROM l UNION ALL SELECT b, a FROM l),
r AS (SELECT doc_id AS x, doc_id AS y FROM documents UNION SELECT r.x, e.b FROM r JOIN e ON r.y = e.a)
SELECT c.x AS doc_id, coalesce(n.n, 0)::BIGINT AS n_shingles, c.component_id
FROM (SELECT x, min(y) AS component_id FROM r GROUP BY x) c LEFT JOIN n ON n.doc_id = c.x
"""

_OP9 = """
WITH d AS (SELECT doc_id, coalesce(text, '') AS t FROM documents),
g AS (SELECT t, max(doc_id) AS keep_id, count(*) AS group_size FROM d GROUP BY t)
SELECT d.doc_id, g.keep_id, g.group_size, d.doc_id = g.keep_id AS kept, sha256(d.t) AS text_sha256 FROM d JOIN g USING (t)
"""

_OP10 = """
WITH p AS (SELECT page_id, octet_length(encode(coalesce(html, '')))::BIGINT AS payload_bytes, sha256(coalesce(html, '')) AS payload_digest FROM pages),
g AS (SELECT payload_digest, min(page_id) AS first_id FROM p WHERE payload_bytes >= 100 GROUP BY 1)
SELECT page_id, payload_bytes, payload_digest, CASE WHEN first_id <> page_id THEN 'revisit' ELSE 'response' END AS record_type,
       CASE WHEN first_id <> page_id THEN first_id END AS refers_to
FROM p LEFT JOIN g USING (payload_digest)
"""


def oracle_sql() -> dict[str, str]:
    return {"op3_mix_sources": _OP3, "op4_secret_scan": _OP4, "op5_decontaminate": _OP5, "op7_ngram_jaccard": _OP7, "op9_exact_dedup": _OP9, "op10_warc": _OP10}
