"""Vector kernels of the structured tasks against their plain forms, and that they take every row."""

import random

import numpy as np
import pyarrow as pa

from pyspark.sql import functions as F

from tinyff.catalog.core import docs
from tinyff.operators import langid, pipelines, postag, preorder, quantize, segment, train
from tinyff.plans.scratch import materialise

SF = "/root/testdata/sf0.001"
ODD = "Das Über die ÄPFEL. ΣΑΣ x1 12 ٣ The 𝔄b Ünglücklichkeit. la nación Rápidamente, \u0000 of the ǅa ª"


def test_silver_sentences_are_the_relational_ones(spark):
    odd = spark.createDataFrame([(-1 - i, ODD, x) for i, x in enumerate(["de", "en", "es", "fr", None, "xx"])], "doc_id long, text string, lang string")
    base = docs(spark, SF).select("doc_id", "text", "lang").unionByName(odd)
    rows, lex = postag.sentence_rows(base), materialise(postag.lexicon(base), "lexicon")
    new = materialise(postag.sentence_lexicon(rows), "lexicon")
    assert new.exceptAll(lex).isEmpty() and lex.exceptAll(new).isEmpty()
    old = materialise(postag.tagged_sentences(postag.silver_tags(base, lex)), "tagged")
    new = materialise(postag.silver_sentences(rows, lex).select(old.columns), "tagged")
    assert new.exceptAll(old).isEmpty() and old.exceptAll(new).isEmpty()


def test_ranks_of_many_sentences():
    rng = random.Random(1)
    tags = [[rng.choice(postag.TAGS) for _ in range(n)] for n in (0, 1, 7, 0, 40, 3)]
    batch = pa.record_batch({"tags": pa.array(tags, pa.list_(pa.string()))})
    assert preorder.silver_ranks(batch).to_pylist() == [preorder.silver_order(x) for x in tags]
    assert preorder.silver_ranks(batch.slice(2)).to_pylist() == [preorder.silver_order(x) for x in tags[2:]]


def test_decoding_follows_the_transition_system():
    rng = random.Random(2)
    toks = [[rng.choice(["a", "bb", "Über", "."]) for _ in range(n)] for n in (0, 1, 2, 3, 12, 30)]
    tags = [[rng.choice(postag.TAGS) for _ in x] for x in toks]
    for kind in ("words", "tags", "tagger_inputs"):
        net = preorder.start(kind)
        words = preorder.Sentences(toks, tags, net.template, kind)
        scorer, steps = preorder.Scorer(net, words), 0
        for x, begin, got in zip(toks, words.start.tolist(), preorder.decode(toks, tags, net)[0], strict=False):
            s = preorder.TransitionSystem(len(x))
            while not s.done:
                places, state = preorder._seen(s, begin)
                s.apply(max(s.legal(), key=scorer(np.array([places]), np.array([state]))[0].__getitem__))
            steps += s.steps
            assert got == s.order
        assert preorder.decode(toks, tags, net)[1] == steps


def test_charts_of_many_sentences():
    rng = random.Random(3)
    rows = [{"tags": x, "rank": preorder.silver_order(x)} for x in ([rng.choice(postag.TAGS) for _ in range(n)] for n in (2, 5, 5, 9, 41, 1))]
    b = preorder.BracketPreorderer().fit(rows)
    assert b.orders([r["tags"] for r in rows]) == [b(r["tags"]) for r in rows] and b.orders([]) == []


def test_tag_preorder_takes_every_sentence(spark):
    """More sentences than one block: none may be left out."""
    sents = spark.range(0, 1500, 1, 1).select(F.col("id").alias("sent_id"), F.array(F.lit("The"), F.lit("cat"), F.col("id").cast("string")).alias("toks"))
    tagger, net = postag.Network.random(postag.template(4), 8, list(postag.TAGS)), preorder.start("tags")
    got = pipelines.tag_preorder(sents, quantize.coded(tagger), net, ["sent_id"]).collect()
    assert sorted(r["sent_id"] for r in got) == list(range(1500)) and all(sorted(r["order"]) == [0, 1, 2] and len(r["tags"]) == 3 for r in got)


def test_greedy_kernel_and_evaluation(spark):
    """Remembered windows give the actions of the decoder; sums are those of plain spans, by every decoder and for rows without a language."""
    rng = random.Random(4)
    sents = [["".join(rng.choice("abcdé漢") for _ in range(rng.randint(1, 6))) for _ in range(rng.randint(1, 9))] for _ in range(60)] + [["𝄞z\u0000q"]]
    texts = ["", *map("".join, sents), "a", "ab", ""]
    for bigrams, hashed in ((False, False), (True, False), (False, True)):
        net, enc = segment.build(sents[:40], sents[:4], 8, bigrams=bigrams, hashed=hashed, epochs=1)
        kernel, want = segment.Greedy(quantize.coded(net), enc), segment.decode(texts, quantize.coded(net), enc)
        for _ in range(2):
            got = kernel(np.frombuffer("".join(texts).encode("utf-32-le"), np.uint32).astype(np.int64), np.array([len(t) for t in texts]))
            assert got.tolist() == [k for x in want for k in x]
    rows = [(["de", None, "en"][i % 3], x) for i, x in enumerate(sents)]
    gold = [segment.spans([k for w in x for k in [0] + [1] * (len(w) - 1)]) for _, x in rows]
    for decider in (segment.one_word, segment.every_char):
        pred = [segment.spans(x) for x in decider(["".join(x) for _, x in rows])]
        for r in segment.evaluate(spark.createDataFrame(rows, "lang string, words array<string>"), decider).collect():
            mine = [i for i, (x, _) in enumerate(rows) if x == r["lang"]]
            assert (r["both"], r["predicted"], r["gold"]) == tuple(sum(len(x) for x in y) for y in ([gold[i] & pred[i] for i in mine], [pred[i] for i in mine], [gold[i] for i in mine]))
            assert r["chars"] == sum(len("".join(rows[i][1])) for i in mine)


def test_steps_without_averaging_copy_nothing(monkeypatch):
    """Without averaging the trained parameters are returned, and gradients of embeddings are added place by place in one dimension."""
    texts, y = ["the cat", "der hund", "a", "zwei"] * 20, np.array([0, 1, 0, 1] * 20)
    t = langid.template(4)
    x, net, seen = langid.bags(texts, t), langid.Network.random(t, 8, ["en", "de"]), []
    plain = np.add

    class Add:
        def __getattr__(self, name):
            return getattr(plain, name)

        def at(self, a, places, values):
            seen.append((a.ndim, a.dtype == values.dtype))
            plain.at(a, places, values)

    monkeypatch.setattr(train.np, "add", Add())
    _, grads = train.loss_and_grad(net, x, y)
    monkeypatch.undo()
    assert set(seen) == {(1, True)}
    moved = net.embeddings[2].copy()
    at = tuple(np.argwhere(np.abs(grads[2]) == np.abs(grads[2]).max())[0])
    values = []
    for step in (1e-2, -1e-2):
        net.embeddings[2] = moved.copy()
        net.embeddings[2][at] += step
        values.append(train.loss_and_grad(net, x, y)[0])
    assert abs((values[0] - values[1]) / 2e-2 - grads[2][at]) < 1e-3
    net.embeddings[2] = moved
    out, history = train.sgd(net, x, y, train.Settings(average=False, epochs=2))
    assert history == [] and not np.allclose(out.w, net.w)
