"""The registry: names, SQL pairs, the flagship, and independence of the llm subpackage."""

import glob
import os
import subprocess
import sys

from conftest import ROOT, SF
from pyspark.sql import functions as F

import __spark_entry__ as entry
from tinyff.registry import QUERIES, SQL
from tinyff.streaming import streams


def test_sql_belongs_to_queries():
    assert set(entry.oracle_sql()) <= set(entry.queries()) and set(SQL) <= set(QUERIES)


def test_flagship(spark):
    assert sum(r["n"] for r in entry.entry(spark).collect()) == 200


def test_library_does_not_import_llm():
    code = "import sys; import tinyff.catalog; assert not any(m.startswith('tinyff.llm') for m in sys.modules)"
    assert subprocess.run([sys.executable, "-c", code], cwd=ROOT).returncode == 0


def test_some_queries(spark):
    for name in ("seg_apply", "split_assign", "twins_dropped", "quant_error_8", "j9_as_of"):
        assert QUERIES[name](spark, SF).count() > 0


def test_late_row_is_dropped(spark):
    stream, rows = streams.late_rows(spark)
    assert streams.drain(streams.tumbling(stream)).agg({"n": "sum"}).first()[0] < rows.count()


def test_staged_files_come_in_order(spark):
    """A file stream orders files by time; the order of ``stage_files`` must not hang on which task ends first."""
    rows = spark.range(400).select(F.col("id").alias("event_id"))
    path = streams.stage_files(rows, 4, "event_id")
    files = sorted(glob.glob(f"{path}/part-*"))
    assert len(files) == 4 and [os.path.getmtime(b) - os.path.getmtime(a) for a, b in zip(files, files[1:], strict=False)] == [1.0] * 3


def test_stream_counts_every_event_once(spark):
    got = {r["event_type"]: r["n"] for r in QUERIES["st6_dedupe"](spark, SF).collect()}
    want = spark.read.parquet(f"{SF}/events.parquet").groupBy("event_type").count().collect()
    assert got == {r["event_type"]: r["count"] for r in want}


def test_costs_are_of_given_tables(spark):
    for name in ("cost_params", "cost_size_kb", "cost_flops", "cost_lstm", "cost_decisions"):
        assert "FileScan parquet" in QUERIES[name](spark, SF)._jdf.queryExecution().executedPlan().toString(), name
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    steps = docs.agg(F.sum(F.octet_length("text"))).first()[0]
    assert QUERIES["cost_lstm"](spark, SF).where("layers = 2").agg(F.sum("steps"), F.sum("flops")).first() == (steps, steps * 2 * 8 * 160 * 320)
    assert QUERIES["cost_flops"](spark, SF).where("classes = 4").agg(F.sum("flops")).first()[0] == docs.count() * 2 * (64 * 208 + 208 * 4)


def test_pruned_scan(spark):
    plan = QUERIES["s2_pruned_and_pushed"](spark, SF)._jdf.queryExecution().executedPlan().toString()
    assert "l_extendedprice" not in plan and "PushedFilters: [IsNotNull(l_quantity)" in plan
