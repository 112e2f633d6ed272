"""Pipelines of tasks in one Arrow pass: no shuffle between the stages."""

from __future__ import annotations

import time
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import langid, postag, preorder, train
from .model import Network


def lang_seg_tag(sents: DataFrame, language: Network, segmenters: dict[str, tuple], taggers: dict[str, Network], keep: list[str]) -> DataFrame:
    """Language, words and tags of unsegmented sentences (column ``text``); the models of the predicted language are used."""
    held = sents.sparkSession.sparkContext.broadcast((language, segmenters, taggers))

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        from . import segment

        language, segmenters, taggers = held.value
        for batch in batches:
            for a in range(0, len(batch), 1024):
                part = batch.iloc[a : a + 256]
                texts = part["text"].tolist()
                z = train.predict(language, langid.bags(texts, language.template))
                langs = [language.classes[i] for i in z.argmax(1)]
                words, tags = [None] * len(texts), [None] * len(texts)
                for lang in set(langs):
                    mine = [i for i, x in enumerate(langs) if x == lang]
                    acts = segment.decode([texts[i] for i in mine], *segmenters[lang])
                    for i, act in zip(mine, acts, strict=True):
                        words[i] = [texts[i][s:e] for s, e in sorted(segment.spans(act))]
                    for i, t in zip(mine, postag.tag_all(taggers[lang], [words[i] for i in mine]), strict=True):
                        tags[i] = t
                yield part[keep].assign(lang_pred=langs, words=words, tags=tags)

    schema = ", ".join(f"{c} {sents.schema[c].dataType.simpleString()}" for c in keep) + ", lang_pred string, words array<string>, tags array<string>"
    return sents.select(*dict.fromkeys([*keep, "text"])).mapInPandas(run, schema)


def tag_preorder(sents: DataFrame, tagger: Network, reorderer: Network, keep: list[str]) -> DataFrame:
    """Predicted tags, then target order, with the seconds that each stage took."""
    held = sents.sparkSession.sparkContext.broadcast((tagger, reorderer))

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        tagger, reorderer = held.value
        tagging = postag.Tagger(tagger)
        for batch in batches:
            if not len(batch):
                continue
            toks = [x.tolist() for x in batch["toks"]]
            t0 = time.perf_counter()
            tags = postag.tag_all(tagger, toks, tagging)
            t1 = time.perf_counter()
            orders = preorder.decode(toks, tags, reorderer)[0]
            n = np.array([len(x) for x in toks], float)
            share = n / max(1.0, n.sum())
            yield batch[keep].assign(tags=tags, order=orders, tag_s=(t1 - t0) * share, order_s=(time.perf_counter() - t1) * share)

    schema = ", ".join(f"{c} {sents.schema[c].dataType.simpleString()}" for c in keep) + ", tags array<string>, order array<int>, tag_s double, order_s double"
    return sents.select(*dict.fromkeys([*keep, "toks"])).mapInPandas(run, schema)


def stage_share(done: DataFrame) -> DataFrame:
    """Share of the tagger in the time of ``tag_preorder``, and tokens a second of one core."""
    total = F.sum("tag_s") + F.sum("order_s")
    return done.agg((F.sum("tag_s") / total).alias("tagger_share"), (F.sum(F.size("order")) / total).alias("tokens_per_second"))
