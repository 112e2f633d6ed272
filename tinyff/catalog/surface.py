"""Streaming and user-function queries."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions import udfs
from ..operators import forward, langid
from ..registry import query
from ..sources.tables import load
from ..streaming import streams
from .core import BUCKET, MODEL, docs, sql_grams


def _events(spark, d, parts=4):
    e = load(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    return streams.events_stream(spark, streams.stage_files(e, parts, "ts"))


@query("st1_watermark_tumbling")
def st1(spark, d):
    return streams.drain(streams.tumbling(_events(spark, d)))


@query("st3_sliding")
def st3(spark, d):
    return streams.drain(streams.sliding(_events(spark, d)))


@query("st4_sessions")
def st4(spark, d):
    return streams.drain(streams.sessions(_events(spark, d)))


@query("st5_late_rows")
def st5(spark, d):
    """The late row is not counted once the watermark has passed its window."""
    stream, _ = streams.late_rows(spark)
    return streams.drain(streams.tumbling(stream))


@query("st6_dedupe", "SELECT event_type, count(*) AS n FROM events GROUP BY event_type")
def st6(spark, d):
    """Every event twice in the stream, once in the result."""
    e = load(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    stream = streams.events_stream(spark, streams.stage_files(e.unionByName(e), 4, "ts"))
    return streams.drain(streams.deduplicated(stream)).groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))


@query("st7_stream_static", "SELECT event_type, count(*) AS n FROM events JOIN customer ON user_id = c_custkey GROUP BY event_type")
def st7(spark, d):
    static = load(spark, d, "customer").select(F.col("c_custkey").alias("user_id"))
    return streams.drain(streams.enriched(_events(spark, d), static, "user_id")).groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))


@query("st8_stream_stream", "SELECT a.event_id AS click, b.event_id AS purchase FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR WHERE a.event_type = 'click' AND b.event_type = 'purchase'")
def st8(spark, d):
    return streams.drain(streams.clicks_to_purchases(_events(spark, d, 1), _events(spark, d, 1)))


@query("st9_user_state", "SELECT user_id, count(*) FILTER (event_type = 'click') AS click, count(*) FILTER (event_type = 'purchase') AS purchase, count(*) FILTER (event_type = 'view') AS view FROM events GROUP BY user_id")
def st9(spark, d):
    """The last state of every user's running profile."""
    got = streams.drain(streams.user_profiles(_events(spark, d, 1), 3650), "update")
    total = F.col("click") + F.col("purchase") + F.col("view")
    return got.groupBy("user_id").agg(F.max_by(F.struct("click", "purchase", "view"), F.struct("batch", total)).alias("s")).select("user_id", "s.*")


@query("st10_restart", "SELECT count(*) AS n FROM events")
def st10(spark, d):
    """A second run from the same checkpoint adds nothing twice."""
    from ..plans.scratch import scratch_path

    mark = scratch_path(spark, "mark")
    stream = _events(spark, d)
    first = streams.drain(stream.select("event_id"), checkpoint=mark)
    again = streams.drain(stream.select("event_id"), checkpoint=mark) if first.count() == 0 else None
    return (first if again is None else first.unionByName(again)).agg(F.count(F.lit(1)).alias("n"))


@query("st11_scored_stream")
def st11(spark, d):
    """Language id on a document stream: counts by ten-hour window and label (the analytic model, vector strategy)."""
    stream = streams.document_stream(spark, streams.stage_files(docs(spark, d), 3, "doc_id"))
    run = forward._vector_predict(MODEL, "ts")
    scored = stream.select("ts", "text").mapInArrow(run, "ts timestamp, label string, score long").withWatermark("ts", "1 hour")
    out = scored.groupBy(F.window("ts", "10 hours").alias("w"), "label").agg(F.count(F.lit(1)).alias("n"))
    return streams.drain(out.select(F.col("w.start").alias("start"), "label", "n"))


@query("ud1_pandas_udf")
def ud1(spark, d):
    return docs(spark, d).select("doc_id", F.round(udfs.junk_share("text"), 6).alias("junk"))


@query("ud2_ud7_language_udf")
def ud2(spark, d):
    """SELECT detect_language(text): an iterator function that loads its model once a task."""
    parts = langid.split_docs(docs(spark, d))
    net = langid.build(langid.sample(parts, "train", 60, 1), langid.sample(parts, "dev", 20, 2), 8, hidden=32, epochs=2)
    udfs.register_language(spark, net)
    docs(spark, d).createOrReplaceTempView("tinyff_udf_docs")
    return spark.sql("SELECT lang, detect_language(text) AS label, count(*) AS n FROM tinyff_udf_docs GROUP BY ALL")


@query("ud3_arrow_udf", "SELECT doc_id, octet_length(encode(text))::BIGINT AS bytes FROM documents")
def ud3(spark, d):
    return docs(spark, d).select("doc_id", udfs.byte_length("text").alias("bytes"))


@query("ud4_grouped_agg", "SELECT lang, avg((source = 'src0')::INT)::DOUBLE AS f1 FROM documents GROUP BY lang")
def ud4(spark, d):
    return docs(spark, d).groupBy("lang").agg(udfs.micro_f1("source", F.lit("src0")).alias("f1"))


@query("ud5_table_function", f"WITH {sql_grams((3,), 'benchmark', 'item_id').replace('lower(', '(')} SELECT x AS gram, count(*) AS n FROM grams GROUP BY x")
def ud5(spark, d):
    spark.udtf.register("tinyff_ngrams", udfs.NGrams)
    load(spark, d, "benchmark").createOrReplaceTempView("tinyff_udtf_items")
    return spark.sql("SELECT gram, count(*) AS n FROM tinyff_udtf_items, LATERAL tinyff_ngrams(text, 3) GROUP BY gram")


@query("ud6_cogroup", "SELECT coalesce(a.lang, b.lang) AS lang, coalesce(a.n, 0)::BIGINT AS left_rows, coalesce(b.n, 0)::BIGINT AS right_rows FROM (SELECT lang, count(*) AS n FROM documents WHERE source = 'src0' GROUP BY 1) a FULL JOIN (SELECT lang, count(*) AS n FROM documents WHERE source = 'src1' GROUP BY 1) b ON a.lang = b.lang")
def ud6(spark, d):
    base = docs(spark, d).select("doc_id", "lang", "source")
    return udfs.cogrouped_difference(base.where("source = 'src0'").select("doc_id", "lang"), base.where("source = 'src1'").select("doc_id", "lang"), "lang")


@query("ud8_sql_function", f"SELECT {BUCKET.format(x='source', v=100)} AS v, count(*) AS n FROM documents GROUP BY 1")
def ud8(spark, d):
    udfs.register_sql_functions(spark)
    docs(spark, d).createOrReplaceTempView("tinyff_fn_docs")
    return spark.sql("SELECT cast(tinyff_bucket(source, 100) AS bigint) AS v, count(*) AS n FROM tinyff_fn_docs GROUP BY 1")

