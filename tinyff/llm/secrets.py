"""Secret scan with an incremental blob ledger, in DataFrame functions only.

Every version of every path is content-addressed by the SHA-256 of its text. The
ledger is two Parquet tables: which (blob, rule, rule version) pairs were scanned,
and what was found. A run scans only pairs that the ledger lacks, one copy of each
blob, appends its findings before its marks (so that a run that died is repeated
and never half trusted), and joins findings back to all paths.

Matches are leftmost and non-overlapping per rule, with code-point offsets and
exclusive ends: the text split at the matches and the matches themselves give all
positions by a running sum of lengths.

Defined cases: a null text is the empty blob and has no findings; texts of any
length are scanned whole; repeated rows are scanned once and reported as often as
they occur; further columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..plans.scratch import materialise, scratch_path, small_side


@dataclass(frozen=True)
class Rule:
    """``pattern`` in Java syntax; ``least`` characters in group ``group``, else the match is dropped; ``rank`` orders kinds."""

    kind: str
    version: int
    rank: int
    pattern: str
    group: int = 0
    least: int = 0
    base: bool = True
    #: Characters that every match contains, if there are any; texts without them are not searched.
    holds: str = ""


#: Fixed patterns of the base kinds, then the rule that this method adds.
RULES = (
    Rule("assign", 1, 0, r"""((?:[pP][aA][sS][sS][wW][oO][rR][dD]|[pP][aA][sS][sS][wW][dD]|[sS][eE][cC][rR][eE][tT]|[tT][oO][kK][eE][nN]|[aA][pP][iI]_?[kK][eE][yY])["']?\x20*[:=]\x20*["']?)([A-Za-z0-9+/_.=-]+)""", 2, 8),
    Rule("access", 1, 1, r"AKIA[A-Z0-9]{12,}", holds="AKIA"),
    Rule("hex", 1, 2, r"[0-9a-f]{32,}"),
    Rule("pem", 1, 3, r"-----BEGIN [A-Z ]{0,40}PRIVATE KEY-----", base=False, holds="PRIVATE KEY-----"),
)

#: With at most so many findings in the ledger, their spans are broadcast.
MOST_FOUND = 100_000

_SCANNED = T.StructType([T.StructField("blob", T.BinaryType()), T.StructField("kind", T.StringType()), T.StructField("version", T.IntegerType())])
_FOUND = T.StructType([*_SCANNED.fields, T.StructField("start", T.LongType()), T.StructField("end", T.LongType())])


def blob_id(text: Column) -> Column:
    return F.unhex(F.sha2(F.coalesce(text, F.lit("")), 256))


def _exists(spark: SparkSession, path: str) -> bool:
    p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(p)


def ledger_table(spark: SparkSession, ledger: str, name: str) -> DataFrame:
    schema = _SCANNED if name == "scanned" else _FOUND
    path = f"{ledger}/{name}"
    return spark.read.schema(schema).parquet(path) if _exists(spark, path) else spark.createDataFrame([], schema)


def _pieces(rule: Rule) -> Column:
    """Per match: the characters before it (since the last one), its own, and those of the group that counts."""
    text = F.col("text")
    whole = F.regexp_extract_all(text, F.lit(rule.pattern), F.lit(0))
    gaps = F.slice(F.transform(F.split(text, rule.pattern, -1), F.length), F.lit(1), F.size(whole))
    counted = whole if rule.group == 0 else F.regexp_extract_all(text, F.lit(rule.pattern), F.lit(rule.group))
    return F.arrays_zip(gaps.alias("gap"), F.transform(whole, F.length).alias("len"), F.transform(counted, F.length).alias("own"))


def findings(blobs: DataFrame, rules: tuple[Rule, ...]) -> DataFrame:
    """(blob, text, kinds) -> one row per match that its rule accepts."""
    # Most texts hold no match: they are found out by one search, and only the others are taken to pieces.
    asked = lambda r: F.array_contains("kinds", r.kind) & (F.contains("text", F.lit(r.holds)) if r.holds else F.lit(True)) & F.col("text").rlike(r.pattern)
    scans = F.array(*[F.struct(F.lit(r.kind).alias("kind"), F.lit(r.version).alias("version"), F.lit(r.least).alias("least"), F.when(asked(r), _pieces(r)).alias("parts")) for r in rules])
    per_kind = blobs.select("blob", F.explode(F.filter(scans, lambda s: F.size(s["parts"]) > 0)).alias("scan")).select("blob", "scan.*")
    parts = per_kind.select("blob", "kind", "version", "least", F.posexplode("parts").alias("i", "part"))
    at = Window.partitionBy("blob", "kind", "version").orderBy("i")
    placed = parts.withColumn("end", F.sum(F.col("part.gap") + F.col("part.len")).over(at).cast("long"))
    return placed.where(F.col("part.own") >= F.col("least")).select("blob", "kind", "version", (F.col("end") - F.col("part.len")).alias("start"), "end")


def _fewer_files(narrow: DataFrame) -> DataFrame:
    """A shuffled table of narrow rows in an eighth of the session's shuffle partitions, as every run adds files to the ledger."""
    return narrow.coalesce(max(1, int(narrow.sparkSession.conf.get("spark.sql.shuffle.partitions")) // 8))


def scan_unseen(versions: DataFrame, ledger: str, rules: tuple[Rule, ...] = RULES, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Brings the ledger up to date for all rows of ``versions``; returns (id, blob), one row per input row."""
    spark = versions.sparkSession
    paths = materialise(versions.select(F.col(id_col).alias("id"), blob_id(F.col(text_col)).alias("blob"), F.length(text_col).alias("chars")), "paths")
    wanted = [F.struct(F.lit(r.kind).alias("kind"), F.lit(r.version).alias("version")) for r in rules]
    asked = paths.where("chars > 0").groupBy("blob").agg(F.min(F.coalesce("id", F.lit(-1))).alias("id"))
    pairs = asked.select("blob", "id", F.inline(F.array(*wanted)))
    unseen = pairs.join(ledger_table(spark, ledger, "scanned"), ["blob", "kind", "version"], "left_anti")
    todo = materialise(_fewer_files(unseen.groupBy("blob", "id").agg(F.collect_set("kind").alias("kinds"))), "unseen")
    one = F.coalesce(F.col(id_col), F.lit(-1)).alias("id")
    texts = versions.select(one, F.col(text_col).alias("text"), blob_id(F.col(text_col)).alias("blob")).where(F.length("text") > 0)
    found = findings(texts.join(small_side(todo), ["blob", "id"]), rules).dropDuplicates(["blob", "kind", "version", "start"])
    _fewer_files(found).write.mode("append").parquet(f"{ledger}/found")
    marks = todo.select("blob", F.explode("kinds").alias("kind"))
    version = F.create_map(*[x for r in rules for x in (F.lit(r.kind), F.lit(r.version))])
    marks.withColumn("version", version[F.col("kind")]).write.mode("append").parquet(f"{ledger}/scanned")
    return paths.select("id", "blob")


def report(paths: DataFrame, ledger: str, rules: tuple[Rule, ...] = RULES, id_col: str = "doc_id") -> DataFrame:
    """Per path: counts of the base kinds, the digest of base spans, and all spans."""
    spark = paths.sparkSession
    rank = {r.kind: r.rank for r in rules}
    current = F.array(*[F.struct(F.lit(r.kind).alias("kind"), F.lit(r.version).alias("version")) for r in rules])
    table = ledger_table(spark, ledger, "found")
    few = table.count() <= MOST_FOUND  # by the footers of the ledger's files
    found = table.dropDuplicates(["blob", "kind", "version", "start"]).where(F.array_contains(current, F.struct("kind", "version")))
    order = F.create_map(*[F.lit(x) for kv in rank.items() for x in kv])
    base = F.col("kind").isin([r.kind for r in rules if r.base])
    span = F.struct("start", order[F.col("kind")].alias("rank"), "end", "kind", base.alias("base"))
    text = lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))
    spans = F.sort_array("all")
    counts = [F.count_if(F.col("kind") == k).alias(f"n_{k}") for k in ("assign", "access", "hex")]
    per_blob = found.groupBy("blob").agg(F.collect_list(span).alias("all"), *counts).select(
        "blob", "n_assign", "n_access", "n_hex",
        F.array_join(F.transform(F.filter(spans, lambda s: s["base"]), text), ",").alias("base_spans"), F.array_join(F.transform(spans, text), ",").alias("spans"),
    )
    zero = lambda c: F.coalesce(F.col(c), F.lit(0)).cast("long").alias(c)
    none = lambda c: F.coalesce(F.col(c), F.lit(""))
    joined = paths.join(F.broadcast(per_blob) if few else per_blob, "blob", "left")
    return joined.select(F.col("id").alias(id_col), zero("n_assign"), zero("n_access"), zero("n_hex"), F.sha2(none("base_spans"), 256).alias("base_sha256"), none("spans").alias("spans"))


def scan(docs: DataFrame, ledger: str | None = None, rules: tuple[Rule, ...] = RULES, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Ledger update and report in one call; without ``ledger`` a fresh one in the shared folder."""
    ledger = ledger or scratch_path(docs.sparkSession, "ledger")
    return report(scan_unseen(docs, ledger, rules, id_col, text_col), ledger, rules, id_col)
