"""The relational surface around the methods: one query per operator family, each with its SQL."""

from __future__ import annotations

from functools import partial

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..plans.scratch import materialise, scratch_path
from ..registry import query
from ..sources.tables import load


def _same(name: str, sql: str, tables: tuple[str, ...], spark_sql: str | None = None) -> None:
    """A query whose text is SQL on both sides; tables become views of this session under private names."""

    def run(spark, d):
        text = spark_sql or sql
        for t in tables:
            load(spark, d, t).createOrReplaceTempView(f"tinyff_{t}")
            text = text.replace("{" + t + "}", f"tinyff_{t}")
        return spark.sql(text)

    plain = sql
    for t in tables:
        plain = plain.replace("{" + t + "}", t)
    query(name, plain)(run)


# Sources, projection, filters.


@query("s1_explicit_schema", "SELECT count(*) AS n, sum(l_quantity) AS quantity FROM lineitem")
def s1(spark, d):
    return load(spark, d, "lineitem").agg(F.count(F.lit(1)).alias("n"), F.sum("l_quantity").alias("quantity"))


@query("s2_pruned_and_pushed", "SELECT l_returnflag AS flag, count(*) AS n FROM lineitem WHERE l_quantity >= 45 AND l_returnflag IN ('A', 'R') GROUP BY 1")
def s2(spark, d):
    return load(spark, d, "lineitem").where((F.col("l_quantity") >= 45) & F.col("l_returnflag").isin("A", "R")).groupBy(F.col("l_returnflag").alias("flag")).agg(F.count(F.lit(1)).alias("n"))


def _round_trip(spark, d, kind):
    path = scratch_path(spark, kind)
    part = load(spark, d, "part").select("p_partkey", "p_brand", "p_size")
    schema = "p_partkey bigint, p_brand string, p_size int"
    if kind == "text":
        part.select(F.concat_ws("|", "p_partkey", "p_brand", "p_size").alias("value")).write.text(path)
        v = F.split("value", r"\|")
        back = spark.read.text(path).select(v[0].cast("long").alias("p_partkey"), v[1].alias("p_brand"), v[2].cast("int").alias("p_size"))
    else:
        part.write.format(kind).save(path)
        back = spark.read.format(kind).schema(schema).load(path)
    return back.groupBy("p_brand").agg(F.count(F.lit(1)).alias("n"), F.sum("p_size").alias("size"))


for _kind in ("json", "csv", "orc", "text"):
    query(f"s3_{_kind}", "SELECT p_brand, count(*) AS n, sum(p_size)::BIGINT AS size FROM part GROUP BY p_brand")(partial(_round_trip, kind=_kind))


@query("s4_partitioned_write", "SELECT lang, count(*) AS n FROM documents WHERE lang IN ('de', 'fr') GROUP BY lang")
def s4(spark, d):
    """Written by language with bounded files a partition; the read prunes to two folders."""
    path = scratch_path(spark, "by-lang")
    load(spark, d, "documents").select("doc_id", "lang").write.partitionBy("lang").option("maxRecordsPerFile", 1_000_000).parquet(path)
    return spark.read.schema("doc_id bigint, lang string").parquet(path).where(F.col("lang").isin("de", "fr")).groupBy("lang").agg(F.count(F.lit(1)).alias("n"))


@query("s5_model_source")
def s5(spark, d):
    """A Python data source that lists the parameters of a stored model."""
    from ..operators import langid, model
    from ..sources.model_source import ModelSource

    path = scratch_path(spark, "model")
    model.save(spark, model.Network.random(langid.template(4), 8, ["de", "en"]), path)
    spark.dataSource.register(ModelSource)
    rows = spark.read.parquet(f"{path}/parameters").toPandas().to_json(orient="records")
    return spark.read.format("tinyff_model").option("parameters", rows).load()


@query("s7_binary_file")
def s7(spark, d):
    """A serialized bit map written and read as whole binary files."""
    path = scratch_path(spark, "bits")
    load(spark, d, "part").select(F.concat_ws(",", "p_partkey", "p_size").alias("value")).coalesce(1).write.text(path)
    return spark.read.format("binaryFile").load(path).agg(F.count(F.lit(1)).alias("files"), F.sum("length").alias("bytes"))


@query("k1_overwrite_partitions", "SELECT lang, sum(n)::BIGINT AS n FROM (SELECT lang, count(*) AS n FROM documents WHERE lang <> 'de' GROUP BY lang UNION ALL SELECT 'de', 1) GROUP BY lang")
def k1(spark, d):
    """Overwrites one partition only (dynamic mode as a write option)."""
    path = scratch_path(spark, "overwrite")
    docs = load(spark, d, "documents").select("doc_id", "lang")
    docs.write.partitionBy("lang").parquet(path)
    docs.where("lang = 'de'").orderBy("doc_id").limit(1).write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("lang").parquet(path)
    return spark.read.schema("doc_id bigint, lang string").parquet(path).groupBy("lang").agg(F.count(F.lit(1)).alias("n"))


_same("p1_derived", "SELECT l_orderkey, l_linenumber, round(l_extendedprice * (1 - l_discount), 4) AS net FROM {lineitem}", ("lineitem",))
_same("p2_predicates", "SELECT p_partkey FROM {part} WHERE (p_name LIKE '%a%' AND p_size BETWEEN 5 AND 25 AND p_brand IN ('Brand#11', 'Brand#12', 'Brand#13')) OR NOT (p_type IS DISTINCT FROM 'X')", ("part",))
_same("p3_case", "SELECT CASE WHEN o_totalprice < 50000 THEN 'low' WHEN o_totalprice < 150000 THEN 'mid' ELSE 'high' END AS band, count(*) AS n FROM {orders} GROUP BY 1", ("orders",))


@query("p4_struct_array", "SELECT vec_id, label, embedding[1]::DOUBLE AS head, len(embedding)::BIGINT AS size FROM embeddings")
def p4(spark, d):
    s = F.struct(F.col("label"), F.col("embedding")[0].alias("head"))
    return load(spark, d, "embeddings").select("vec_id", s.alias("s"), F.size("embedding").cast("long").alias("size")).select("vec_id", "s.label", F.col("s.head").cast("double").alias("head"), "size")


# Joins.

_ROUND = "round(sum(l_extendedprice), 2)"
_same("j1_broadcast", "SELECT r_name, count(*) AS n FROM {nation} JOIN {region} ON n_regionkey = r_regionkey GROUP BY r_name", ("nation", "region"), "SELECT /*+ BROADCAST({region}) */ r_name, count(*) AS n FROM {nation} JOIN {region} ON n_regionkey = r_regionkey GROUP BY r_name")
_same("j2_sort_merge", "SELECT quality, toxic, count(*) AS n FROM {documents} JOIN {labels} USING (doc_id) GROUP BY quality, toxic", ("documents", "labels"), "SELECT /*+ MERGE({labels}) */ quality, toxic, count(*) AS n FROM {documents} JOIN {labels} USING (doc_id) GROUP BY quality, toxic")
_same("j3_shuffle_hash", "SELECT o_orderstatus, count(*) AS n FROM {orders} JOIN {lineitem} ON o_orderkey = l_orderkey GROUP BY o_orderstatus", ("orders", "lineitem"), "SELECT /*+ SHUFFLE_HASH({orders}) */ o_orderstatus, count(*) AS n FROM {orders} JOIN {lineitem} ON o_orderkey = l_orderkey GROUP BY o_orderstatus")
for _type in ("LEFT", "RIGHT", "FULL"):
    _same(f"j4_{_type.lower()}", f"SELECT count(*) AS n, count(doc_id) AS left_rows, count(label_id) AS right_rows FROM (SELECT doc_id FROM {{documents}} WHERE lang = 'en') a {_type} JOIN (SELECT doc_id AS label_id FROM {{labels}}) b ON doc_id = label_id", ("documents", "labels"))
_same("j5_semi", "SELECT c_custkey FROM {customer} WHERE EXISTS (SELECT 1 FROM {orders} WHERE o_custkey = c_custkey AND o_totalprice > 200000)", ("customer", "orders"))
_same("j6_anti", "SELECT c_custkey FROM {customer} WHERE NOT EXISTS (SELECT 1 FROM {orders} WHERE o_custkey = c_custkey)", ("customer", "orders"))
_same("j7_theta", "SELECT a.n_name AS x, b.n_name AS y FROM {nation} a JOIN {nation} b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey", ("nation",))
_same("j11_null_safe", "SELECT count(*) AS n FROM (SELECT nullif(s_nationkey, 3) AS k FROM {supplier}) a JOIN (SELECT nullif(n_nationkey, 3) AS k FROM {nation}) b ON NOT (a.k IS DISTINCT FROM b.k)", ("supplier", "nation"))
_same("j13_lateral", "SELECT n_name, t.best FROM {nation}, LATERAL (SELECT max(s_acctbal) AS best FROM {supplier} WHERE s_nationkey = n_nationkey) t", ("nation", "supplier"))


@query("j8_range", "SELECT a.conv_id, count(*) AS n FROM (SELECT DISTINCT conv_id FROM conversations) a JOIN (SELECT doc_id FROM documents) b ON b.doc_id BETWEEN a.conv_id AND a.conv_id + 5 GROUP BY a.conv_id")
def j8(spark, d):
    """Ranges are cut into buckets, so the join is on equality, with the bounds as its condition."""
    width = 8
    spans = load(spark, d, "conversations").select("conv_id").distinct().select("conv_id", F.explode(F.sequence(F.floor(F.col("conv_id") / width), F.floor((F.col("conv_id") + 5) / width))).alias("b"))
    points = load(spark, d, "documents").select("doc_id", F.floor(F.col("doc_id") / width).alias("b"))
    return spans.join(points, "b").where(F.col("doc_id").between(F.col("conv_id"), F.col("conv_id") + 5)).groupBy("conv_id").agg(F.count(F.lit(1)).alias("n"))


@query("j9_as_of", "SELECT event_id, (SELECT max_by(p.event_id, (p.ts, p.event_id)) FROM events p WHERE p.user_id = e.user_id AND p.event_type = 'view' AND (p.ts, p.event_id) <= (e.ts, e.event_id)) AS last_view FROM events e WHERE event_type = 'purchase'")
def j9(spark, d):
    """The last view of the user at or before each purchase: one window over the user's events, no self-join."""
    at = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    seen = F.last(F.when(F.col("event_type") == "view", F.col("event_id")), ignorenulls=True).over(at)
    return load(spark, d, "events").select("event_id", "event_type", seen.alias("last_view")).where("event_type = 'purchase'").select("event_id", "last_view")


@query("j10_interval", "SELECT a.event_id AS click, count(*) AS n FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR WHERE a.event_type = 'click' AND b.event_type = 'purchase' GROUP BY a.event_id")
def j10(spark, d):
    e = load(spark, d, "events")
    a, b = e.where("event_type = 'click'").alias("a"), e.where("event_type = 'purchase'").alias("b")
    within = (F.col("b.ts") > F.col("a.ts")) & (F.col("b.ts") <= F.col("a.ts") + F.expr("INTERVAL 1 HOUR"))
    return a.join(b, (F.col("a.user_id") == F.col("b.user_id")) & within).groupBy(F.col("a.event_id").alias("click")).agg(F.count(F.lit(1)).alias("n"))


@query("j12_salted", "SELECT event_type, count(*) AS n, round(sum(value), 4) AS total FROM events JOIN (SELECT event_type, count(*) AS c FROM events GROUP BY 1) USING (event_type) GROUP BY event_type")
def j12(spark, d):
    """Few and hot keys: the large side gets a salt, the small one is repeated once a salt."""
    salts = 8
    e = load(spark, d, "events").withColumn("salt", F.pmod(F.xxhash64("event_id"), F.lit(salts)).cast("int"))
    small = e.groupBy("event_type").agg(F.count(F.lit(1)).alias("c")).withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    partial_sums = e.join(small, ["event_type", "salt"]).groupBy("event_type", "salt").agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("total"))
    return partial_sums.groupBy("event_type").agg(F.sum("n").alias("n"), F.round(F.sum("total"), 4).alias("total"))


# Aggregation.

_same("a1_hash", "SELECT l_returnflag, l_linestatus, count(*) AS n, sum(l_quantity) AS q FROM {lineitem} GROUP BY l_returnflag, l_linestatus", ("lineitem",))
_same("a2_distinct", "SELECT count(DISTINCT user_id) AS users, count(DISTINCT event_type) AS types FROM {events}", ("events",))
for _g, _by in (("sets", "GROUPING SETS ((lang), (source), ())"), ("cube", "CUBE (lang, source)"), ("rollup", "ROLLUP (lang, source)")):
    _same(f"a3_{_g}", f"SELECT lang, source, count(*) AS n FROM {{documents}} GROUP BY {_by}", ("documents",))


@query("a4_pivot", "SELECT event_type, " + ", ".join(f"count(*) FILTER (user_id % 3 = {k}) AS u{k}" for k in range(3)) + " FROM events GROUP BY event_type")
def a4(spark, d):
    e = load(spark, d, "events").withColumn("k", F.concat(F.lit("u"), (F.col("user_id") % 3).cast("string")))
    return e.groupBy("event_type").pivot("k", ["u0", "u1", "u2"]).agg(F.count(F.lit(1))).na.fill(0)


@query("a5_approx_distinct")
def a5(spark, d):
    """The sketch against the exact number."""
    return load(spark, d, "lineitem").agg(F.approx_count_distinct("l_partkey", 0.02).alias("approx"), F.countDistinct("l_partkey").alias("exact"))


_same("a6_percentiles", "SELECT o_orderstatus, percentile_cont(0.5) WITHIN GROUP (ORDER BY o_totalprice) AS median FROM {orders} GROUP BY o_orderstatus", ("orders",))


@query("a7_collect", "SELECT n_regionkey::BIGINT AS region, string_agg(n_name, ',' ORDER BY n_name) AS names FROM nation GROUP BY 1")
def a7(spark, d):
    return load(spark, d, "nation").groupBy(F.col("n_regionkey").cast("long").alias("region")).agg(F.array_join(F.array_sort(F.collect_list("n_name")), ",").alias("names"))


@query("a8_max_by", "SELECT o_custkey, arg_max(o_orderkey, (o_totalprice, o_orderkey)) AS largest, arg_min(o_orderkey, (o_totalprice, o_orderkey)) AS smallest FROM orders GROUP BY o_custkey")
def a8(spark, d):
    by = F.struct("o_totalprice", "o_orderkey")
    return load(spark, d, "orders").groupBy("o_custkey").agg(F.max_by("o_orderkey", by).alias("largest"), F.min_by("o_orderkey", by).alias("smallest"))


_same("a9_filtered", "SELECT count(*) FILTER (WHERE value > 50) AS high, count(*) FILTER (WHERE event_type = 'error') AS errors FROM {events}", ("events",))
_same("a10_moments", "SELECT round(var_samp(l_quantity), 6) AS var, round(stddev_pop(l_discount), 6) AS dev, round(corr(l_quantity, l_extendedprice), 6) AS r, round(regr_slope(l_extendedprice, l_quantity), 4) AS slope FROM {lineitem}", ("lineitem",))
_same("a11_bits", "SELECT label, bit_or(vec_id) AS o, bit_and(vec_id) AS a, bit_xor(vec_id) AS x FROM {embeddings} GROUP BY label", ("embeddings",))


@query("a12_count_min")
def a12(spark, d):
    """A count-min table of hashed words: its estimate is never below the count."""
    words = load(spark, d, "documents").select(F.explode(F.split(F.lower("text"), r"[ \n]+")).alias("w"))
    counts = materialise(words.groupBy("w").agg(F.count(F.lit(1)).alias("n")), "words")
    cells = counts.select("w", "n", F.posexplode(F.array(*[F.pmod(F.xxhash64("w", F.lit(r)), F.lit(2048)) for r in range(4)])).alias("r", "c"))
    table = cells.groupBy("r", "c").agg(F.sum("n").alias("t"))
    est = cells.join(F.broadcast(table), ["r", "c"]).groupBy("w").agg(F.min("t").alias("estimate"), F.first("n").alias("n"))  # 4 x 2,048 rows
    return est.agg(F.count(F.lit(1)).alias("words"), F.sum((F.col("estimate") < F.col("n")).cast("long")).alias("below"), F.avg(F.col("estimate") - F.col("n")).alias("mean_excess"))


_same("a13_listagg", "SELECT r_name, string_agg(n_name, '|' ORDER BY n_name) AS names FROM {nation} JOIN {region} ON n_regionkey = r_regionkey GROUP BY r_name", ("nation", "region"), "SELECT r_name, listagg(n_name, '|') WITHIN GROUP (ORDER BY n_name) AS names FROM {nation} JOIN {region} ON n_regionkey = r_regionkey GROUP BY r_name")


@query("a14_two_phase", "SELECT source, count(*) AS n, sum(n_chars)::BIGINT AS chars FROM documents GROUP BY source")
def a14(spark, d):
    """A hot source is summed by salt first, then by source."""
    docs = load(spark, d, "documents").select("source", "n_chars", F.pmod(F.xxhash64("doc_id"), F.lit(16)).alias("salt"))
    return docs.groupBy("source", "salt").agg(F.count(F.lit(1)).alias("n"), F.sum("n_chars").alias("chars")).groupBy("source").agg(F.sum("n").alias("n"), F.sum("chars").alias("chars"))


# Windows, sorting, sets, subqueries.

_W = "OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey)"
_same("x1_ranks", f"SELECT o_orderkey, row_number() {_W} AS rn, rank() {_W} AS rk, dense_rank() {_W} AS dr, ntile(4) {_W} AS nt, round(percent_rank() {_W}, 6) AS pr, round(cume_dist() {_W}, 6) AS cd FROM {{orders}}", ("orders",), f"SELECT o_orderkey, cast(row_number() {_W} AS bigint) AS rn, cast(rank() {_W} AS bigint) AS rk, cast(dense_rank() {_W} AS bigint) AS dr, cast(ntile(4) {_W} AS bigint) AS nt, round(percent_rank() {_W}, 6) AS pr, round(cume_dist() {_W}, 6) AS cd FROM {{orders}}")
_same("x2_lag_lead", "SELECT event_id, lag(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS before, lead(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS after FROM {events}", ("events",))
_same("x3_rows_frame", "SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 6) AS mean3 FROM {events}", ("events",))
_same("x4_range_frame", "SELECT event_id, count(*) OVER (PARTITION BY event_type ORDER BY ts RANGE BETWEEN INTERVAL 1 HOUR PRECEDING AND CURRENT ROW) AS n FROM {events}", ("events",), "SELECT event_id, count(*) OVER (PARTITION BY event_type ORDER BY cast(ts AS timestamp) RANGE BETWEEN INTERVAL 1 HOUR PRECEDING AND CURRENT ROW) AS n FROM {events}")
_same("x5_first_last_nth", "SELECT o_orderkey, first_value(o_orderkey) OVER w AS f, last_value(o_orderkey) OVER w AS l, nth_value(o_orderkey, 2) OVER w AS s FROM {orders} WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)", ("orders",))
_same("x6_islands", "SELECT user_id, event_type, count(*) AS n, min(event_id) AS first_id FROM (SELECT *, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) - row_number() OVER (PARTITION BY user_id, event_type ORDER BY ts, event_id) AS g FROM {events}) t GROUP BY user_id, event_type, g", ("events",))
_same("x7_running_sum", "SELECT l_orderkey, l_linenumber, sum(l_quantity) OVER (PARTITION BY l_orderkey ORDER BY l_linenumber) AS upto FROM {lineitem}", ("lineitem",))
_same("t1_sort", "SELECT c_custkey, c_name FROM {customer} ORDER BY c_acctbal DESC, c_custkey", ("customer",))
_same("t2_limit_offset", "SELECT c_custkey FROM {customer} ORDER BY c_acctbal DESC, c_custkey LIMIT 20 OFFSET 10", ("customer",))
_same("t3_top_per_group", "SELECT o_custkey, o_orderkey FROM (SELECT *, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS k FROM {orders}) t WHERE k <= 3", ("orders",))


@query("t4_sort_within", "SELECT count(*) AS n FROM orders")
def t4(spark, d):
    return load(spark, d, "orders").repartition(4, "o_custkey").sortWithinPartitions("o_custkey", "o_orderdate").agg(F.count(F.lit(1)).alias("n"))


_VOCAB = "SELECT unnest(string_split(lower(text), ' ')) AS w FROM documents WHERE lang = '{}'"
_SVOCAB = "SELECT explode(split(lower(text), ' ', -1)) AS w FROM {{documents}} WHERE lang = '{}'"
for _name, _op in (("u1_union_all", "UNION ALL"), ("u2_intersect", "INTERSECT"), ("u2_intersect_all", "INTERSECT ALL"), ("u3_except", "EXCEPT"), ("u3_except_all", "EXCEPT ALL"), ("u4_distinct", "UNION")):
    _same(_name, f"SELECT count(*) AS n FROM ({_VOCAB.format('de')} {_op} {_VOCAB.format('es')}) t", ("documents",), f"SELECT count(*) AS n FROM ({_SVOCAB.format('de').replace('{{', '{').replace('}}', '}')} {_op} {_SVOCAB.format('es').replace('{{', '{').replace('}}', '}')}) t")
_same("v1_scalar", "SELECT count(*) AS n FROM {orders} WHERE o_totalprice > (SELECT avg(o_totalprice) FROM {orders})", ("orders",))
_same("v2_exists", "SELECT count(*) AS n FROM {documents} d WHERE EXISTS (SELECT 1 FROM {labels} l WHERE l.doc_id = d.doc_id AND l.toxic = 1)", ("documents", "labels"))
_same("v3_correlated", "SELECT o_orderkey FROM {orders} o WHERE o_totalprice > (SELECT 1.5 * avg(o_totalprice) FROM {orders} i WHERE i.o_custkey = o.o_custkey)", ("orders",))
_same("v4_cte", "WITH n AS (SELECT o_custkey, count(*) AS c FROM {orders} GROUP BY o_custkey) SELECT c, count(*) AS customers FROM n GROUP BY c", ("orders",))
_same("v5_recursive", "WITH RECURSIVE t(i, a, b) AS (SELECT 0, 0, 1 UNION ALL SELECT i + 1, b, a + b FROM t WHERE i < 30) SELECT i, a FROM t", ())

# Functions.

_same("f1_strings", "SELECT p_partkey, lower(p_name) AS l, trim(p_type) AS t, translate(p_brand, '#', '-') AS tr, replace(p_name, 'a', 'o') AS r, regexp_replace(p_type, '[AEIOU]', '_', 'g') AS x FROM {part}", ("part",), "SELECT p_partkey, lower(p_name) AS l, trim(p_type) AS t, translate(p_brand, '#', '-') AS tr, replace(p_name, 'a', 'o') AS r, regexp_replace(p_type, '[AEIOU]', '_') AS x FROM {part}")
_same("f2_lengths", "SELECT doc_id, length(text)::BIGINT AS chars, octet_length(encode(text))::BIGINT AS bytes, substr(text, 3, 5) AS part FROM {documents}", ("documents",), "SELECT doc_id, cast(length(text) AS bigint) AS chars, cast(octet_length(text) AS bigint) AS bytes, substr(text, 3, 5) AS part FROM {documents}")
_same("f3_split_distance", "SELECT n_name, concat_ws('-', n_name, 'x') AS c, levenshtein(n_name, 'FRANCE')::BIGINT AS dist FROM {nation}", ("nation",), "SELECT n_name, concat_ws('-', n_name, 'x') AS c, cast(levenshtein(n_name, 'FRANCE') AS bigint) AS dist FROM {nation}")
_same("f4_digests", "SELECT doc_id, md5(text) AS m, sha256(text) AS s FROM {documents}", ("documents",), "SELECT doc_id, md5(text) AS m, sha2(text, 256) AS s FROM {documents}")
_same("f5_encodings", "SELECT item_id, hex(encode(text)) AS h, base64(encode(text)) AS b FROM {benchmark}", ("benchmark",), "SELECT item_id, hex(encode(text, 'UTF-8')) AS h, replace(base64(encode(text, 'UTF-8')), '\r\n', '') AS b FROM {benchmark}")
_same("f6_urls", "SELECT page_id, regexp_extract(url, '^([a-z]+)://', 1) AS scheme, regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) AS host, regexp_extract(url, '^[a-z]+://[^/?#]+([^?#]*)', 1) AS path FROM {pages}", ("pages",), "SELECT page_id, parse_url(url, 'PROTOCOL') AS scheme, parse_url(url, 'HOST') AS host, parse_url(url, 'PATH') AS path FROM {pages}")
_same("f7_dates", "SELECT o_orderkey, year(o_orderdate)::BIGINT AS y, month(o_orderdate)::BIGINT AS m, quarter(o_orderdate)::BIGINT AS q, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS t, strftime(o_orderdate + INTERVAL 10 DAY, '%Y-%m-%d') AS later FROM {orders}", ("orders",), "SELECT o_orderkey, cast(year(o_orderdate) AS bigint) AS y, cast(month(o_orderdate) AS bigint) AS m, cast(quarter(o_orderdate) AS bigint) AS q, date_format(date_trunc('month', o_orderdate), 'yyyy-MM-dd') AS t, date_format(o_orderdate + INTERVAL 10 DAY, 'yyyy-MM-dd') AS later FROM {orders}")
_same("f8_math", "SELECT vec_id, round(exp(x), 6) AS e, round(ln(abs(x) + 1), 6) AS l, round(sqrt(abs(x)), 6) AS s, greatest(x, 0) AS relu, (vec_id & 7) AS b, (vec_id % 7) AS m FROM (SELECT vec_id, embedding[1]::DOUBLE AS x FROM {embeddings}) t", ("embeddings",), "SELECT vec_id, round(exp(x), 6) AS e, round(ln(abs(x) + 1), 6) AS l, round(sqrt(abs(x)), 6) AS s, greatest(x, 0D) AS relu, (vec_id & 7) AS b, pmod(vec_id, 7) AS m FROM (SELECT vec_id, cast(embedding[0] AS double) AS x FROM {embeddings}) t")
_same("f9_arrays", "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x)), 5) AS norm2, len(list_filter(embedding, lambda x: x > 0))::BIGINT AS positive, round(list_max(embedding)::DOUBLE, 6) AS top FROM {embeddings}", ("embeddings",), "SELECT vec_id, round(aggregate(embedding, 0D, (a, x) -> a + cast(x AS double) * x), 5) AS norm2, cast(size(filter(embedding, x -> x > 0)) AS bigint) AS positive, round(cast(array_max(embedding) AS double), 6) AS top FROM {embeddings}")


@query("f10_maps", "SELECT label, min(vec_id) AS lo, max(vec_id) AS hi FROM embeddings GROUP BY label")
def f10(spark, d):
    m = F.map_from_arrays(F.array(F.lit("lo"), F.lit("hi")), F.array(F.min("vec_id"), F.max("vec_id")))
    made = load(spark, d, "embeddings").groupBy("label").agg(m.alias("m"))
    return made.select("label", F.transform_values("m", lambda k, v: v)["lo"].alias("lo"), F.map_filter("m", lambda k, v: k == "hi")["hi"].alias("hi"))


@query("f11_inline", "SELECT vec_id, i::BIGINT AS i, embedding[i + 1]::DOUBLE AS x FROM embeddings, (SELECT unnest(range(0, 64)) AS i)")
def f11(spark, d):
    return load(spark, d, "embeddings").select("vec_id", F.posexplode("embedding").alias("i", "x")).select("vec_id", F.col("i").cast("long").alias("i"), F.col("x").cast("double").alias("x"))


_same("f12_json", "SELECT event_id, (props ->> '$.n')::BIGINT AS n FROM {events}", ("events",), "SELECT event_id, from_json(props, 'n bigint').n AS n FROM {events}")
_same("f13_variant", "SELECT sum((props ->> '$.n')::BIGINT)::BIGINT AS n FROM {events}", ("events",), "SELECT sum(variant_get(parse_json(props), '$.n', 'bigint')) AS n FROM {events}")

# Batch twins of the streaming windows.

_same("tumbling_counts", "SELECT time_bucket(INTERVAL '1 hour', ts) AS start, event_type, count(*) AS n FROM {events} GROUP BY 1, 2", ("events",), "SELECT cast(window(cast(ts AS timestamp), '1 hour').start AS timestamp_ntz) AS start, event_type, count(*) AS n FROM {events} GROUP BY 1, 2")
_same("sliding_counts", "SELECT time_bucket(INTERVAL '30 minutes', ts) - k * INTERVAL '30 minutes' AS start, count(*) AS n FROM {events}, (SELECT unnest([0, 1]) AS k) GROUP BY 1", ("events",), "SELECT cast(window(cast(ts AS timestamp), '1 hour', '30 minutes').start AS timestamp_ntz) AS start, count(*) AS n FROM {events} GROUP BY 1")
_same(
    "session_counts",
    "SELECT user_id, min(ts) AS start, count(*) AS n FROM (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) <= INTERVAL 2 HOUR THEN 0 ELSE 1 END AS new FROM {events}) a) b GROUP BY user_id, s",
    ("events",),
    "SELECT user_id, cast(session_window(cast(ts AS timestamp), '2 hours').start AS timestamp_ntz) AS start, count(*) AS n FROM {events} GROUP BY user_id, session_window(cast(ts AS timestamp), '2 hours')",
)


@query("k4_tables", "SELECT 'documents' AS name, count(*) AS n FROM documents UNION ALL SELECT 'events', count(*) FROM events UNION ALL SELECT 'pages', count(*) FROM pages")
def k4(spark, d):
    """Row counts by table name, as a check of the explicit schemas."""
    parts = [load(spark, d, t).agg(F.lit(t).alias("name"), F.count(F.lit(1)).alias("n")) for t in ("documents", "events", "pages")]
    return parts[0].unionByName(parts[1]).unionByName(parts[2])


