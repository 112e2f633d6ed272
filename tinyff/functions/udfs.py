"""User-defined functions over a model that is loaded once a task, and their SQL names."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql import types as T
from pyspark.sql.functions import arrow_udf, pandas_udf, udtf


def language_udf(spark: SparkSession, net):
    """An iterator function text -> language; the network is broadcast."""
    from ..operators import langid, train

    held = spark.sparkContext.broadcast(net)

    @pandas_udf(T.StringType())
    def detect(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        n = held.value
        for texts in batches:
            z = train.predict(n, langid.bags(texts, n.template)) if len(texts) else np.zeros((0, 1))
            yield pd.Series(np.array(n.classes, object)[z.argmax(1)])

    return detect


def register_language(spark: SparkSession, net, name: str = "detect_language") -> None:
    spark.udf.register(name, language_udf(spark, net))


@pandas_udf(T.DoubleType())
def junk_share(texts: pd.Series) -> pd.Series:
    """Share of junk characters of each text."""
    return texts.fillna("").map(lambda s: sum(c in "#$%&*|!" for c in s) / max(1, len(s))).astype(float)


@arrow_udf(T.LongType())
def byte_length(texts: pa.Array) -> pa.Array:
    import pyarrow.compute as pc

    return pc.binary_length(texts.cast(pa.large_binary())).cast(pa.int64())


@pandas_udf(T.DoubleType())
def micro_f1(gold: pd.Series, pred: pd.Series) -> float:
    """A grouped aggregate: micro-averaged F1 of one label a row."""
    return float((gold == pred).mean())


@udtf(returnType=T.StructType([T.StructField("pos", T.IntegerType()), T.StructField("gram", T.StringType())]))
class NGrams:
    """ngrams(text, n): the character n-grams with their places."""

    def eval(self, text: str, n: int):
        for i in range(len(text or "") - n + 1):
            yield i, text[i : i + n]


def register_sql_functions(spark: SparkSession) -> None:
    """Pure SQL scalar functions: nothing leaves the JVM."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION tinyff_bucket(x STRING, v INT) RETURNS INT RETURN cast(pmod(cast(conv(substring(md5(x), 1, 8), 16, 10) AS bigint), v) AS int)")


def cogrouped_difference(left, right, key: str):
    """Cogrouped map: rows of both sides per key (counts)."""

    def both(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        k = (a if len(a) else b)[key].iloc[0]
        return pd.DataFrame({key: [k], "left_rows": [len(a)], "right_rows": [len(b)]})

    return left.groupBy(key).cogroup(right.groupBy(key)).applyInPandas(both, f"{key} string, left_rows long, right_rows long")
