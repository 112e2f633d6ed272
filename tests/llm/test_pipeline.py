"""The pipeline's filtering stages against brute force on the smallest tables."""

import re

import corpus_pipeline
from conftest import SF
from pyspark.sql import functions as F

from llm_brute import LOW, brute_components
from tinyff.llm import mixing


def test_stages_follow_brute_force(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    names = [n for n, _ in corpus_pipeline.STAGES]
    assert names == ["toxicity", "exact_dedup", "ngram_jaccard", "decontamination", "mixing"]
    rows = {r["doc_id"]: r["text"] for r in docs.collect()}
    kept = {r["doc_id"] for r in corpus_pipeline.drop_exact_copies(spark, docs, SF).collect()}
    last = {t: max(i for i, x in rows.items() if x == t) for t in rows.values()}
    assert kept == set(last.values())
    distinct = docs.where(docs.doc_id.isin(*kept))
    order = sorted(kept)
    near = brute_components([rows[i] for i in order], 5, 80)
    want = {i for at, i in enumerate(order) if near[at][1] == at}
    assert {r["doc_id"] for r in corpus_pipeline.drop_near_copies(spark, distinct, SF).collect()} == want

    words = lambda s: re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", (s or "").translate(LOW))
    windows = {}
    for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect():
        w = words(r["text"])
        k = min(13, len(w))
        windows.setdefault(k, set()).update(tuple(w[i : i + k]) for i in range(len(w) - k + 1))
    clean = set()
    for i, t in rows.items():
        w, hit = words(t), set()
        for k, known in windows.items():
            hit |= {p for s in range(len(w) - k + 1) if tuple(w[s : s + k]) in known for p in range(s, s + k)}
        if not hit or 20 * len(hit) < len(w):
            clean.add(i)
    out = corpus_pipeline.drop_contaminated(spark, docs, SF)
    assert {r["doc_id"] for r in out.collect()} == clean and out.columns == docs.columns
    assert corpus_pipeline.drop_toxic(spark, docs, SF).columns == docs.columns
    mixed = corpus_pipeline.mix_sources(spark, docs, SF)
    assert mixed.where("copy = 2").count() > 0 and set(docs.columns) <= set(mixed.columns)
    assert corpus_pipeline.drop_near_copies(spark, docs.limit(0), SF).count() == 0


def test_null_ids_in_every_stage(spark):
    bench = spark.read.parquet(f"{SF}/benchmark.parquet").first()["text"]
    base = [f"word{i}" for i in range(60)]
    own, twin, lone = " ".join(base), " ".join(base[:-1] + ["changed"]), " ".join(f"lone{i}" for i in range(40))
    rows = [(1, own), (None, own), (None, twin), (None, lone), (None, None), (2, ""), (None, bench), (3, "x y z")]
    schema = "doc_id long, text string, lang string, source string, n_chars long"
    docs = spark.createDataFrame([(i, t, "en", "s", 0) for i, t in rows], schema)
    texts = lambda df: sorted((r["doc_id"] is None, r["text"] or "") for r in df.collect())
    every = sorted((i is None, t or "") for i, t in rows)

    def without(*gone):
        return [x for x in every if x not in gone]

    assert texts(corpus_pipeline.drop_toxic(spark, docs, SF)) == every
    assert texts(corpus_pipeline.drop_exact_copies(spark, docs, SF)) == without((True, own), (True, ""))
    assert texts(corpus_pipeline.drop_near_copies(spark, docs, SF)) == without((True, own), (True, twin))
    assert texts(corpus_pipeline.drop_contaminated(spark, docs, SF)) == without((True, bench))
    copies = corpus_pipeline.mix_sources(spark, docs, SF)
    taken = mixing.mix(docs).where("doc_id IS NULL").agg({"copies": "sum"}).first()[0]
    assert copies.where("doc_id IS NULL").count() == taken > 0
    assert copies.where("doc_id IS NULL AND text IS NULL").count() == 0


def test_repeated_ids_are_judged_by_their_texts(spark):
    """One id under several texts: each row stays or goes by its own text; columns of any name pass through."""
    bench = spark.read.parquet(f"{SF}/benchmark.parquet").first()["text"]
    base = [f"word{i}" for i in range(60)]
    own, twin, lone = " ".join(base), " ".join(base[:-1] + ["changed"]), " ".join(f"lone{i}" for i in range(40))
    data = [(1, own), (1, lone), (2, own), (3, twin), (3, bench), (4, lone), (4, lone), (None, bench), (None, bench), (5, None), (5, "")]
    schema = "doc_id long, text string, lang string, source string, n_chars long"
    docs = spark.createDataFrame([(i, t, "en", "s", 0) for i, t in data], schema)
    for c in ("score", "predicted", "n_words", "n_hit", "hit_ranges", "items", "contaminated", "id", "rep", "n", "copy", "digest", "kept"):
        docs = docs.withColumn(c, F.lit(f"own {c}"))
    show = lambda df: sorted((-1 if r["doc_id"] is None else r["doc_id"], r["text"] or "") for r in df.collect())

    exact = corpus_pipeline.drop_exact_copies(spark, docs, SF)
    assert show(exact) == sorted([(2, own), (3, twin), (3, bench), (4, lone), (5, "")])
    near = corpus_pipeline.drop_near_copies(spark, docs, SF)
    assert [x for x in show(near) if x[1] in (own, twin)] == [(2, own)]
    clean = corpus_pipeline.drop_contaminated(spark, docs, SF)
    assert show(clean) == sorted((-1 if i is None else i, t or "") for i, t in data if t != bench)
    kind = corpus_pipeline.drop_toxic(spark, docs, SF)
    mixed = corpus_pipeline.mix_sources(spark, docs, SF)
    for out in (exact, near, clean, kind):
        assert out.columns == docs.columns and out.where("score = 'own score' AND contaminated = 'own contaminated'").count() == out.count()
    assert mixed.columns == [*docs.columns, "mix_copy"]
    for _, stage in corpus_pipeline.STAGES:
        assert stage(spark, docs.limit(0), SF).count() == 0
