"""Corpus pipeline: documents that are clean, distinct, uncontaminated and mixed to target weights.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame; it is written as
Parquet and read again as the next stage's ``docs``. All but the last return the
columns of ``docs``. The last gives every taken document as often as the mix takes
it, numbered by ``copy``.

Defined cases are those of the operators: null and empty texts pass the filters
(equal ones once), rows of one id are judged each by its own text, rows without an
id (or with one under which several texts stand) are documents by their texts and
go where an equal or near copy has an id, extra columns pass through under any
name, and an empty table goes through all stages.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tinyff.llm import decontaminate, exact_dedup, jaccard, mixing, toxicity
from tinyff.llm.rows import ROW_KEY, with_row_key
from tinyff.plans.scratch import materialise, small_side


def _kept_by(docs: DataFrame, found: DataFrame, names: dict[str, str], condition: str) -> DataFrame:
    """The rows of ``found`` under ``condition``, with the columns of ``docs`` under their own names again."""
    return found.where(condition).drop(*names).withColumnsRenamed({v: k for k, v in names.items()}).select(*docs.columns)


def _aside(docs: DataFrame, made: tuple[str, ...]) -> tuple[DataFrame, dict[str, str]]:
    """``docs`` with the columns whose names an operator makes renamed, and those names."""
    names = {c: f"_doc_{c}" for c in docs.columns if c in made}
    return docs.withColumnsRenamed(names), names


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rejects documents whose toxicity score is 0.5 or more; learns from labels that are not held out."""
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet")
    model = toxicity.fit(docs, toxicity.train_labels(labels))
    rows, names = _aside(docs, ("score", "predicted"))
    return _kept_by(docs, toxicity.score(rows, model), names, "predicted = 0")


def drop_exact_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of equal texts the row with the largest id stays."""
    return exact_dedup.deduplicated(docs)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near duplicates (five words a shingle, similarity 0.8) the document with the smallest id stays."""
    keyed = with_row_key(docs, "doc_id", "text", lowest=False, distinct_texts=True)
    groups = jaccard.similarity_classes(keyed, ROW_KEY, k=5, percent=80)
    dropped = small_side(materialise(groups.where(F.col(ROW_KEY) != F.col("component_id")).select(ROW_KEY).distinct(), "dropped"))
    return keyed.join(dropped, ROW_KEY, "left_anti").select(*docs.columns)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rejects documents of which a twentieth or more of the words lie in benchmark windows, row by row."""
    rows, names = _aside(docs, ("n_words", "n_hit", "hit_ranges", "items", "contaminated"))
    found = decontaminate.contamination(rows, spark.read.parquet(f"{sf_dir}/benchmark.parquet"), keep=rows.columns)
    return _kept_by(docs, found, names, "NOT contaminated")


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The mix of sources; documents appear as often as they are taken."""
    return mixing.mixed(docs)


STAGES = [
    ("toxicity", drop_toxic),
    ("exact_dedup", drop_exact_copies),
    ("ngram_jaccard", drop_near_copies),
    ("decontamination", drop_contaminated),
    ("mixing", mix_sources),
]

#: The first stage is a trained model, which SQL cannot express; tests compare the others with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = materialise(stage(spark, docs, sf_dir), f"stage-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
