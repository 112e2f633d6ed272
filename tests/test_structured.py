"""Transition systems, segmentation, preordering, Bloom maps, measures."""

from itertools import permutations

import numpy as np
import pytest

from pyspark.sql import functions as F

from tinyff.operators import bloommap, langid, metrics, pipelines, postag, preorder, quantize, segment, train


def test_segmentation_system():
    s = segment.TransitionSystem(list("abc"))
    assert s.legal() == [segment.SPLIT]
    for a in (segment.SPLIT, segment.MERGE, segment.SPLIT):
        s.apply(a)
    assert s.words == ["ab", "c"] and s.legal() == []
    with pytest.raises(ValueError):
        segment.TransitionSystem(list("a")).apply(segment.MERGE)


def test_singletons_become_unknown():
    assert "q" not in segment.vocabulary(["aab", "abq"], 1)


@pytest.mark.parametrize("key", ["first", "last", "min"])
@pytest.mark.parametrize("n", range(1, 6))
def test_every_order_is_reachable(n, key):
    for p in permutations(range(n)):
        for eager in (True, False) if key == "first" else (False,):
            s = preorder.TransitionSystem(n, key)
            actions = preorder.derivation(list(p), eager, key)
            for a in actions:
                s.apply(a)
            assert s.done and [p[i] for i in s.order] == list(range(n))
            assert len(actions) == 2 * n - 1 + 2 * s.swaps
            assert s.swaps <= n * (n - 1) // 2


def test_any_derivation_gives_a_permutation():
    rng = np.random.default_rng(1)
    for n in range(1, 9):
        for k in range(45):
            s = preorder.TransitionSystem(n, ["first", "last", "min"][k % 3])
            while not s.done:
                s.apply(int(rng.choice(s.legal())))
            assert sorted(s.order) == list(range(n)) and s.steps == 2 * n - 1 + 2 * s.swaps and s.swaps <= n * (n - 1) // 2


def test_scores():
    assert preorder.frs([0, 1, 2]) == 100.0 and preorder.frs([0]) == 100.0
    assert preorder.frs([2, 1, 0]) == 0.0


def test_score_columns(spark):
    df = spark.createDataFrame([([0, 1, 2],), ([2, 1, 0],), ([0],), ([1, 0, 2],)], "p array<int>")
    r = df.select(metrics.frs_pairs(df.p), metrics.frs_chunks(df.p), metrics.inversions(df.p), metrics.kendall(df.p)).collect()
    assert list(r[0]) == [100.0, 100.0, 0, 1.0] and list(r[1]) == [0.0, 0.0, 3, -1.0] and list(r[2]) == [100.0, 100.0, 0, 1.0]
    assert r[3][0] == pytest.approx(preorder.frs([1, 0, 2]))


@pytest.mark.parametrize("variant,priors", [("pairs", False), ("pairs", True), ("tree", False)])
def test_map_never_loses_a_key(spark, variant, priors):
    rows = [(f"w{i}", 0 if i % 3 else i % 7) for i in range(300)]
    held = bloommap.build(spark.createDataFrame(rows, "k string, v int"), "k", "v", 16.0, variant, priors)
    got = [held.get(k) for k, _ in rows]
    assert None not in got and np.mean([g == v for g, (_, v) in zip(got, rows, strict=True)]) > 0.97
    assert np.mean([held.get(f"x{i}") is not None for i in range(300)]) < 0.2


def test_micro_f1_is_accuracy(spark):
    df = spark.createDataFrame([("a", "a"), ("a", "b"), ("b", "b"), ("c", "a")], "g string, p string")
    assert metrics.micro_f1(df, "g", "p").first()[0] == pytest.approx(0.5)


def test_segmenter_scores_blocks_as_it_would_step_by_step():
    sents = [["ab", "c", "abc"], ["c", "ab"], ["abcab"], ["b", "a", "c", "ab"]] * 10
    for bigrams in (False, True):
        net, enc = segment.build(sents, sents[:4], 8, bigrams=bigrams, epochs=2)
        net = quantize.coded(net)
        for text in ["", "a", "ab", "abcabc", "qqabcbacabab", "漢字ab"]:
            actions, total = [], 0.0
            for at in range(len(text)):
                uni, bi = enc.grid(text)
                past = np.array([[actions[-1] if actions else 2, actions[-2] if len(actions) > 1 else 2]])
                z = net.logits(train.embed(net, segment._bags(uni[at : at + 1], bi[at : at + 1] if bigrams else None, past)))[0]
                actions.append(0 if at == 0 else int(z[1] > z[0]))
            assert segment.decode([text], net, enc) == [actions] == segment.decode([text, "abc"], net, enc)[:1]
            assert segment.decode([text], net, enc, beam=4)[0][:1] == [0][: len(text)]


def test_longest_match_has_no_longest_word():
    word = "x" * 60
    assert segment.MaxMatch([[word, "y"]])([word + "y"]) == [[0] + [1] * 59 + [0]]


@pytest.mark.parametrize("kind", ["words", "tags", "tagger_inputs"])
def test_preorder_scores_are_those_of_the_bags(kind):
    t = preorder.template(kind)
    net = preorder.Network.random(t, 8, preorder.ACTIONS, seed=2)
    toks, tags = [["The", "cat", "sat", "."], ["Go"], ["a", "b"]], [["FUNC", "NOUN", "VERB", "PUNCT"], ["VERB"], ["SYM", "NUM"]]
    words = preorder.Sentences(toks, tags, t, kind)
    places = np.array([[-1, -1, -1, -1, 0, 1], [0, 3, 1, 2, 3, -1], [4, 4, -1, -1, -1, -1], [5, 6, -1, -1, 6, -1]])
    states = np.array([[2, 0], [4, 8], [0, 1], [3, 9]])
    assert np.allclose(preorder.Scorer(net, words)(places, states), net.logits(train.embed(net, words.state_bags(t, places, states))), atol=1e-5)
    net.resources["kind"] = kind
    orders, steps, swaps = preorder.decode(toks, tags, net)
    assert [sorted(o) for o in orders] == [[0, 1, 2, 3], [0], [0, 1]] and steps == 2 * 7 - 3 + 2 * swaps


@pytest.mark.parametrize("kind", ["words", "tags", "tagger_inputs"])
def test_preorder_few_sentences_go_on_alone(kind, monkeypatch):
    net = preorder.Network.random(preorder.template(kind), 8, preorder.ACTIONS, seed=3)
    net.resources["kind"] = kind
    rng = np.random.default_rng(4)
    toks = [[f"w{x}" for x in rng.integers(0, 30, n)] for n in (0, 1, 2, 40, 7, 3)]
    tags = [[postag.TAGS[x] for x in rng.integers(0, len(postag.TAGS), len(s))] for s in toks]
    passes, score = [], preorder.Scorer.__call__
    monkeypatch.setattr(preorder.Scorer, "__call__", lambda self, places, states: passes.append(len(places)) or score(self, places, states))
    alone = preorder.decode(toks, tags, net)
    assert len(passes) < alone[1] / 2  # a pass over arrays for each step of one long sentence costs far more than its scores
    monkeypatch.setattr(preorder, "FEW", 0)
    assert preorder.decode(toks, tags, net) == alone and passes
    monkeypatch.setattr(preorder, "FEW", 3)
    assert preorder.decode(toks, tags, net) == alone


@pytest.mark.parametrize("often", [preorder.SHIFT, preorder.SWAP])
def test_preorder_repeated_actions_are_scored_together(often, monkeypatch):
    rng = np.random.default_rng(7)
    toks = [[f"w{x}" for x in rng.integers(0, 30, n)] for n in (120, 60, 90)]
    passes, score = [], preorder.Scorer.__call__
    monkeypatch.setattr(preorder.Scorer, "__call__", lambda self, places, states: passes.append(len(places)) or score(self, places, states))
    for seed in range(6):
        net = preorder.Network.random(preorder.template("words"), 8, preorder.ACTIONS, seed=seed)
        net.resources["kind"] = "words"
        net.b[often] += 0.3 * seed
        passes.clear()
        monkeypatch.setattr(preorder, "FEW", 12)
        together = preorder.decode(toks, None, net)
        assert seed < 5 or together[1] / 2 > len(passes) > 0
        monkeypatch.setattr(preorder, "FEW", 0)
        assert preorder.decode(toks, None, net) == together



def test_tagger_inputs_are_those_of_the_bags(spark):
    lex = spark.createDataFrame([("cat", 3), ("sat", 5)], "word string, cluster int")
    held = bloommap.build(lex, "word", "cluster", 16.0)
    t = postag.template(4, True)
    net = postag.Network.random(t, 8, list(postag.TAGS))
    net.resources["clusters"] = held
    sents = [["The", "cat", "sat", "."], [], ["CAT"], ["a", "the"]]
    words = postag.Words(sents, t, held)
    bags = words.token_bags(t)
    assert np.allclose(words.h0(net), train.embed(net, bags), atol=1e-6) and len(bags) == 7
    assert [bags.ids[s][:4].tolist() for s in (8,)] == [[held.find(bloommap.key_hash([w]))[0] + 2 for w in ("the", "cat", "sat", ".")]]
    assert bags.ids[7][0] == bags.ids[7][4] == 0 and bags.ids[9][3] == 0  # outside the sentence
    assert [len(x) for x in postag.tag_all(net, sents)] == [4, 0, 1, 2]


def test_map_positions_agree_with_spark(spark):
    words = ["a", "Straße", "漢字", "w" * 40, ""]
    df = spark.createDataFrame([(w, v) for w in words for v in (0, 1, 63)], "w string, v int")
    rows = df.select("w", "v", *[bloommap.position(F.xxhash64("w"), F.col("v"), F.lit(i), 1000).alias(f"p{i}") for i in (0, 5)]).collect()
    for r in rows:
        key = bloommap.key_hash([r["w"]])
        assert [int(bloommap.positions(key, r["v"], i, 1000)[0]) for i in (0, 5)] == [r["p0"], r["p5"]]


def test_bracketing_learns_and_leaves_long_sentences():
    rows = [{"tags": ["NOUN", "VERB", "FUNC"], "rank": [0, 2, 1]}, {"tags": ["VERB", "NOUN"], "rank": [1, 0]}]
    b = preorder.BracketPreorderer(longest=5).fit(rows)
    assert b(["NOUN", "VERB", "FUNC"]) == [0, 2, 1] and b(["VERB", "NOUN"]) == [1, 0] and b(["VERB"] * 6) == list(range(6))


def test_tagger_template_against_single_words():
    """The bags of every slot, from n-grams taken one word at a time."""
    from tinyff.functions.hashing import gram_buckets

    t = postag.template(4)
    v = [g.vocab for g in t.groups]
    for toks in (["The", "CAT", "x", "42", "—"], ["é"]):
        bags = postag.Words([toks], t).token_bags(t)
        padded = ["\x00", *toks, "\x00"]
        for i in range(len(toks)):
            w = toks[i].lower()
            want = [gram_buckets(f"^{padded[i + k].lower()}$", 2, v[0]) for k in range(3)] + [gram_buckets(f"^{w}$", 3, v[1])]
            want += [gram_buckets("^" + w[:3], len(w[:3]) + 1, v[2]), gram_buckets(w[-3:] + "$", len(w[-3:]) + 1, v[2]), [postag._shape(toks[i])]]
            assert [bags.ids[s][bags.offsets[s][i] : bags.offsets[s][i + 1]].tolist() for s in range(len(want))] == [(list(x) or [0]) for x in want]


def test_fused_pipeline_is_its_stages(spark):
    texts = ["thecatsat", "derhund", "", "catcat"]
    language = langid.build(langid.Sample(["the cat"] * 20 + ["der hund"] * 20, np.array([0] * 20 + [1] * 20), ["en", "de"]), langid.Sample(["the", "der"], np.array([0, 1]), ["en", "de"]), 4, 16, epochs=8)
    seg = {x: segment.build([["the", "cat"], ["der", "hund"]] * 10, [["the"]], 4) for x in ("en", "de")}
    tag = {x: postag.Network.random(postag.template(4), 8, list(postag.TAGS), seed=k) for k, x in enumerate(("en", "de"))}
    got = {r["text"]: r for r in pipelines.lang_seg_tag(spark.createDataFrame([(t,) for t in texts], "text string"), language, seg, tag, ["text"]).collect()}
    for t in texts:
        lang = language.classes[int(train.predict(language, langid.bags([t], language.template)).argmax())]
        words = [t[a:b] for a, b in sorted(segment.spans(segment.decode([t], *seg[lang])[0]))]
        assert (got[t]["lang_pred"], got[t]["words"], got[t]["tags"]) == (lang, words, list(postag.tag_all(tag[lang], [words])[0]))
