"""Directions of the published tables that hold on the given tables, on trained runs of the catalog."""

from collections import defaultdict

import pytest

from tinyff.catalog import QUERIES

SF = "/root/testdata/sf0.01"


def rows(spark, name):
    return [r.asDict() for r in QUERIES[name](spark, SF).collect()]


def test_language_identification(spark):
    """More dimensions in codes beat fewer exact ones in size and score; codes keep the labels; the shortest fragments are hardest."""
    got = {(r["model"], r["width"]): r for r in rows(spark, "langid_trained")}
    for width in (5, 10, 20):
        full, coded, six = (got[m, width] for m in ("16 dims", "16 dims, 8 bits", "6 dims"))
        assert coded["agree"] >= 0.99 and coded["kb"] < six["kb"] < full["kb"] / 2
        assert coded["micro_f1"] >= full["micro_f1"] - 0.005
    assert got["16 dims, 8 bits", 5]["micro_f1"] >= got["6 dims", 5]["micro_f1"]
    assert got["16 dims", 5]["micro_f1"] < got["16 dims", 10]["micro_f1"] < got["16 dims", 50]["micro_f1"] + 1e-9


def test_tagging(spark):
    """Clusters from a map help, at half the dimensions too, with fewer weights and operations than the plain tagger."""
    got = {r["model"]: r for r in rows(spark, "tagger_trained") if r["lang"] == "mean"}
    plain, full, half, near = (got[m] for m in ("vanilla", "clusters", "clusters, half dims", "clusters from neighbours"))
    assert full["accuracy"] > half["accuracy"] > plain["accuracy"] and near["accuracy"] > plain["accuracy"]
    assert half["params"] < plain["params"] < full["params"] and half["flops"] < plain["flops"]
    assert abs(plain["accuracy"] - got["vanilla, float"]["accuracy"]) < 0.005 and plain["kb"] < got["vanilla, float"]["kb"] / 2
    assert got["bytes to spans"]["params"] > half["params"] and got["bytes to spans"]["flops"] > 36 * half["flops"]


def test_segmentation(spark):
    """Small bigram embeddings beat larger character embeddings at less than their size; hashing hurts."""
    by = defaultdict(dict)
    for r in rows(spark, "segmenter_trained"):
        by[r["model"]][r["lang"]] = r
    mean = {m: sum(r["char_accuracy"] for r in x.values()) / len(x) for m, x in by.items()}
    kb = {m: next(iter(x.values()))["kb"] for m, x in by.items()}
    assert mean["bigrams, 64 dims"] > mean["unigrams, 256 dims"] and kb["bigrams, 64 dims"] < kb["unigrams, 256 dims"]
    assert mean["hashed, 64 dims"] < mean["unigrams, 64 dims"] and mean["linear"] < mean["linear, conjunctions"]


def test_preordering(spark):
    """Predicted tags beat the tagger's inputs, which beat words alone."""
    got = {r["model"]: r for r in rows(spark, "preorder_trained")}
    assert got["predicted tags"]["frs"] > got["tagger inputs"]["frs"] > got["words"]["frs"] > got["reverse"]["frs"]
    assert got["words"]["kb"] < got["tagger inputs"]["kb"]


def test_three_stages_take_fewer_operations(spark):
    got = rows(spark, "pipeline_lang_seg_tag")
    assert {r["tab"] for r in got} == {"documents", "conversations"} and all(r["fewer_operations"] > 12 for r in got)
    assert all(r["lang_right"] > 0.9 for r in got if r["lang"] is not None) and all(r["words"] == r["tags"] for r in got)


@pytest.mark.parametrize("name", ["segmenter_grid", "preorder_grid"])
def test_grids_by_task_measures(spark, name):
    got = rows(spark, name)
    assert len(got) == 8 and max(r["metric"] for r in got) > min(r["metric"] for r in got)
