"""Layers, gradients, quantization, costs."""

import hashlib
from collections import Counter

import numpy as np
import pytest

from tinyff.functions import hashing
from tinyff.operators import bloommap, bytespan, cost, forward, langid, model, postag, quantize, train
from tinyff.operators.features import FeatureGroup, Template


def small():
    t = Template((FeatureGroup("a", 7, 3, slots=2), FeatureGroup("b", 5, 2)))
    net = model.Network.random(t, 6, ["x", "y", "z"], seed=3)
    rng = np.random.default_rng(0)
    rows = [[rng.integers(0, 7, 3), rng.integers(0, 7, 1), rng.integers(0, 5, 2)] for _ in range(8)]
    return net, train.Bags.of([0, 0, 1], rows), rng.integers(0, 3, 8)


@pytest.mark.parametrize("combine", ["mean", "sum"])
def test_gradients_match_finite_differences(combine):
    net, x, y = small()
    net.embeddings = [e.astype(np.float64) for e in net.embeddings]
    net.w, net.c, net.beta, net.b = (p.astype(np.float64) for p in (net.w, net.c, net.beta, net.b))
    _, grads = train.loss_and_grad(net, x, y, 0.01, combine)
    for p, g in zip(net.parameters(), grads, strict=True):
        for i in list(np.ndindex(p.shape))[::3]:
            old = p[i]
            p[i] = old + 1e-5
            up = train.loss_and_grad(net, x, y, 0.01, combine)[0]
            p[i] = old - 1e-5
            down = train.loss_and_grad(net, x, y, 0.01, combine)[0]
            p[i] = old
            assert abs((up - down) / 2e-5 - g[i]) < 1e-4


def test_training_learns_and_averages():
    texts = ["the of and with"] * 40 + ["der die und das"] * 40
    y = np.array([0] * 40 + [1] * 40)
    t = langid.template(4)
    net, _ = train.sgd(model.Network.random(t, 8, ["en", "de"]), langid.bags(texts, t), y, train.Settings(lr=0.5, epochs=40))
    assert (train.predict(net, langid.bags(["and of the", "und das die"], t)).argmax(1) == [0, 1]).all()


def test_rate_decays():
    s = train.Settings(lr=0.1, decay=0.5, decay_steps=10)
    assert train.rate(s, 0) == 0.1 and abs(train.rate(s, 20) - 0.025) < 1e-12


@pytest.mark.parametrize("bits", [8, 4, 2])
def test_quantization_error_is_at_most_half_a_scale(bits):
    rows = np.array([[0, 0, 0], [1, -2, 3], [-5, -1, -2], [4, 4, 4], [0.001, 100, -3]], np.float32)
    q, s = quantize.quantize_matrix(rows, bits, np.float32)
    assert (np.abs(rows - quantize.restore_matrix(q, s)) <= s / 2 + 1e-5).all()
    assert (q[0] == 0).all() and s[0] == 0


def test_costs_follow_the_shape():
    t = langid.template(16)
    assert cost.params(t, 208, 66) == 11000 * 16 + 64 * 208 + 208 + 208 * 66 + 66
    assert cost.flops(64, 208, 66) == 2 * 64 * 208 + 2 * 208 * 66
    assert abs(cost.size_bytes(t, 208, 66, 8, 2) / 1024 - 302) / 302 < 0.03
    assert cost.lstm_flops(1, 160) == 8 * 160 * 320


def test_strategies_agree_and_edges(spark):
    rows = [(1, ""), (2, "a"), (3, "###"), (4, "Straße é 漢字 😀"), (5, None), (6, "the quick brown fox")]
    df = spark.createDataFrame(rows, "k long, text string")
    m = model.AnalyticModel()
    got = [sorted(map(tuple, forward.predict(df, m, "k", strategy=s).collect())) for s in ("vector", "relational", "inrow")]
    assert got[0] == got[1] == got[2] and len(got[0]) == 6


@pytest.mark.parametrize(("orders", "vocab"), [((1, 2, 3, 4), (100, 500, 1000, 5000)), ((3, 1), (50, 20)), ((2,), (1000,)), ((2, 5, 2), (30, 400, 70))])
def test_in_row_hashes_each_ngram_of_a_text_once(spark, orders, vocab):
    """Equal n-grams of a row are counted before they are hashed; ends of texts, whose windows are short, give no longer n-gram."""
    texts = ["", None, "a", "aa", "aaa", "aaaa", "abcab", "ab" * 3000, "b\nA\n" * 40, "😀😁😀a😀", "İi\x00ß\x00 漢字漢字", " .\r\n\u2028 ", "the quick brown fox the quick"]
    df, m = spark.createDataFrame(list(enumerate(texts)), "k long, text string"), model.AnalyticModel(orders=orders, vocab=vocab)
    got = forward.predict(df, m, "k", strategy="inrow")
    plan = got._jdf.queryExecution().executedPlan().toString()
    assert "sort_array" in plan and "split(" not in plan and "Exchange" not in plan and "Python" not in plan and "InArrow" not in plan
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, forward.predict(df, m, "k").collect()))


def test_sums_by_the_kernel_are_those_of_the_join(spark):
    """Embeddings come from the vector kernel: no n-gram becomes a row; rows of one key count together, as in SQL."""
    rows = [(1, ""), (2, "a"), (3, "###"), (4, "Straße é 漢字 😀"), (5, None), (6, "the quick brown fox"), (6, "again"), (7, "ab" * 500)]
    df, m = spark.createDataFrame(rows, "k long, text string"), model.AnalyticModel()
    sums = forward.group_sums(df, "k", "text", m)
    assert "Generate" not in sums._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in forward.gram_counts(df, "k", "text", m)._jdf.queryExecution().executedPlan().toString()
    for how in ("mean", "sum"):
        joined = forward.embed(forward.gram_counts(df, "k", "text", m), "k", m, how)
        assert sorted(map(tuple, forward.combined(sums, "k", m, how).collect())) == sorted(map(tuple, joined.collect()))


def test_profiles_make_no_row_of_an_ngram(spark):
    """Counted before anything is exploded; rows of one key count together."""
    df = spark.createDataFrame([(1, "abab"), (1, "Ab"), (2, None), (3, "")], "k long, text string")
    prof = langid.profile(df, "k", "text", (1, 2), 50)
    assert "MapInArrow" in prof._jdf.queryExecution().executedPlan().toString()
    want = Counter(int(hashlib.md5(g.encode()).hexdigest()[:8], 16) % 50 for t in ("abab", "ab") for n in (1, 2) for g in (t[i : i + n] for i in range(len(t) - n + 1)))
    assert {(r["k"], r["v"]): r["cnt"] for r in prof.collect()} == {(1, v): n for v, n in want.items()}


def test_model_store(spark, tmp_path):
    net, x, _ = small()
    model.save(spark, net, str(tmp_path / "m"))
    back = model.load(spark, str(tmp_path / "m"))
    assert np.allclose(train.predict(net, x), train.predict(back, x))


def test_vector_scoring_needs_no_exchange(spark):
    df = spark.range(5).selectExpr("id AS k", "'abc' AS text")
    plan = forward.predict(df, model.AnalyticModel(), "k")._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan


@pytest.mark.parametrize("granularity", ["row", "group", "matrix"])
@pytest.mark.parametrize("bits", [16, 8, 4, 2])
def test_scores_of_codes_are_those_of_decoded_embeddings(bits, granularity):
    net, x, _ = small()
    net.resources["bytes"] = 1000
    coded = quantize.coded(net, bits, np.float32, granularity, group=2)
    plain = quantize.restored(coded)
    assert np.allclose(train.predict(coded, x), train.predict(plain, x), atol=1e-5)
    full = train.Bags([0, 0, 1], [np.tile(np.arange(7), 40)] * 2 + [np.tile(np.arange(5), 40)], [np.array([0, 140, 280]), np.array([0, 140, 280]), np.array([0, 100, 200])])
    assert np.allclose(train.predict(coded, full), train.predict(plain, full), atol=1e-4)  # by counts instead of gathered rows
    scales = {"row": 12, "group": 7 * 2 + 5, "matrix": 2}[granularity]
    assert cost.size_kb(coded) == pytest.approx((cost.size_bytes(net.template, 6, 3, bits, 0, 1000) + 4 * scales) / 1024)
    assert cost.size_kb(net) == pytest.approx((cost.size_bytes(net.template, 6, 3) + 1000) / 1024)


def test_bags_of_a_block_are_those_of_its_texts():
    texts = ["", "a", "straße 漢字 😀", "the quick brown fox", "aaaa"]
    for n in (1, 2, 4):
        ids, off = hashing.gram_bags(texts, n, 97)
        md5 = hashing.Md5Buckets(n, 97)
        block = hashing.Block(texts)
        again = [md5(block).tolist(), md5(block).tolist()]
        assert again[0] == again[1] == [int(hashlib.md5(t[i : i + n].encode()).hexdigest()[:8], 16) % 97 for t in texts for i in range(len(t) - n + 1)]
        for k, t in enumerate(texts):
            assert ids[off[k] : off[k + 1]].tolist() == (hashing.gram_buckets(t, n, 97).tolist() or [0])


def test_nearest_neighbours_by_blocks(spark):
    rng = np.random.default_rng(2)
    texts = ["".join(rng.choice(list("abcde "), rng.integers(0, 40))) for _ in range(60)] + ["same text", "same text"]
    rows = langid.sparse_profiles(spark.createDataFrame(list(enumerate(texts)), "k long, text string"), ["k"], "text", size=50)
    labels = rows.select("k", "k").toDF("k", "lab")
    dense = {r["k"]: dict(zip(r["at"], r["cnt"], strict=True)) for r in rows.collect()}
    got = {r["k"]: r["other"] for r in langid.nearest_neighbour(rows.where("k < 20 OR k = 61"), rows.where("k >= 20"), labels, "k", "lab", 50, block=7).collect()}
    for k in [*range(20), 61]:
        sims = {o: round(sum(c * dense[o].get(v, 0) for v, c in dense[k].items()) / np.sqrt(sum(c * c for c in dense[o].values())), 6) for o in range(20, 62) if dense[o]}
        best = max(sims.values(), default=0)
        assert got.get(k) == (min(o for o, s in sims.items() if s == best) if best > 0 else None)


def test_model_store_keeps_the_map(spark, tmp_path):
    words = spark.createDataFrame([(f"w{i}", i % 5) for i in range(50)], "word string, cluster int")
    net = model.Network.random(postag.template(4, True), 8, ["x", "y"])
    net.resources |= {"clusters": bloommap.build(words, "word", "cluster"), "bytes": 7}
    model.save(spark, net, str(tmp_path / "m"))
    back = model.load(spark, str(tmp_path / "m"))
    keys = bloommap.key_hash([f"w{i}" for i in range(80)])
    assert (back.resources["clusters"].find(keys) == net.resources["clusters"].find(keys)).all() and back.resources["bytes"] == 7


def test_recurrent_gradients_and_spans():
    net = bytespan.ByteSpanNetwork(["A", "B"], 6, 2, dtype=np.float64)
    texts, spans = [b"ab cd", b"x"], [[(0, 2, "A"), (3, 2, "B")], [(0, 1, "B")]]
    _, grads = net.loss_and_grad(texts, spans)
    for p, g in zip(net.parameters(), grads, strict=True):
        for i in list(np.ndindex(p.shape))[::53]:
            old = p[i]
            p[i] = old + 1e-5
            up = net.loss_and_grad(texts, spans)[0]
            p[i] = old - 1e-5
            down = net.loss_and_grad(texts, spans)[0]
            p[i] = old
            assert abs((up - down) / 2e-5 - g[i]) < 1e-6
    net = bytespan.ByteSpanNetwork(["A", "B"], 16, 2).fit(list(zip(texts, spans, strict=True)) * 16, epochs=250, rate=1e-2)
    assert net.write(texts) == [set(s) for s in spans]


def test_segments_cover_all_tokens():
    toks = ["a" * 30, "é" * 20, "x", "y" * 100, "z"]
    cut = list(bytespan.segments(toks))
    assert [(a, b) for _, a, b in cut] == [(0, 1), (1, 3), (3, 4), (4, 5)] and max(len(t) for t, _, _ in cut) == bytespan.SEGMENT
    for text, a, b in cut:
        for at, n, tag in bytespan.gold_spans(toks[a:b], toks[a:b]):
            assert text[at : at + n] == tag.encode()[: bytespan.SEGMENT]


def _some_texts(n: int, seed: int) -> list[str]:
    rng = np.random.default_rng(seed)
    words = ["".join(rng.choice(list("abcdeé"), rng.integers(1, 6))) for _ in range(60)]
    return [" ".join(rng.choice(words, rng.integers(1, 30))) for _ in range(n)]


def test_neighbours_by_bands_list_no_pairs(spark):
    """Against every pair that shares a band; equal texts tie, so the smallest id wins."""
    from pyspark.sql import functions as F

    from tinyff.plans import scratch

    texts = _some_texts(300, 5)
    texts[200] = texts[120]
    texts[250] = ""
    rows = scratch.materialise(langid.sparse_profiles(spark.createDataFrame(list(enumerate(texts)), "k long, text string"), ["k"], "text", size=40), "sparse")
    coded = {r["k"]: r for r in langid.bands(rows, "k", size=40).collect()}
    long = rows.select("k", F.inline(F.arrays_zip(F.col("at").alias("v"), "cnt")))
    sign = lambda i: F.when(F.pmod(F.xxhash64("v", F.lit(3000 + i)), F.lit(2)) == 0, F.col("cnt")).otherwise(-F.col("cnt"))
    for r in long.groupBy("k").agg(*[F.sum(sign(i)).alias(f"s{i}") for i in range(96)]).collect():
        assert coded[r["k"]]["codes"] == [sum((r[f"s{12 * b + i}"] > 0) << i for i in range(12)) for b in range(8)]
    dense = np.zeros((len(texts), 40))
    for k, r in coded.items():
        dense[k, r["at"]] = r["cnt"]
    length = np.sqrt((dense**2).sum(1))
    want, exact = {}, {}
    for q in range(0, 100):
        for found, same in ((want, True), (exact, False)):
            near = [(-np.floor(dense[q] @ (dense[o] / length[o]) * 1e6 + 0.5) / 1e6, o) for o in range(100, 300) if length[o] and (not same or any(a == b for a, b in zip(coded[q]["codes"], coded[o]["codes"], strict=True)))]
            near = [x for x in near if x[0] < 0]
            if near:
                found[q] = min(near)[1]
    test, known = rows.where("k < 100"), rows.where("k >= 100")
    got = langid.neighbour_by_bands(test, known, "k", 40, block=30)
    assert {r["k"]: r["other"] for r in got.collect()} == want and want != exact
    held = spark.createDataFrame([(k, "x") for k in range(300)], "k long, lab string")
    assert {r["k"]: r["other"] for r in langid.nearest_neighbour(test, known, held, "k", "lab", 40).collect()} == exact
    plan = got._jdf.queryExecution().toString()
    assert "Join" not in plan and "codes" not in plan  # written rounds: no table of pairs


@pytest.mark.parametrize("sim", ["cosine", "skew", "rank"])
def test_sparse_prototypes_are_those_of_the_rows(spark, sim):
    from pyspark.sql import functions as F

    texts = [*_some_texts(60, 6), "", "zz"]
    df = spark.createDataFrame([(i, t, "pqr"[i % 3]) for i, t in enumerate(texts)], "k long, text string, lab string")
    sparse, long = langid.sparse_profiles(df, ["k", "lab"], "text", size=40), langid.profile(df, "k", "text", size=40)
    known, test = F.col("k") % 2 == 0, F.col("k") % 2 == 1
    protos = langid.prototypes(sparse.where(known), None, "k", "lab")
    slow = langid.prototypes(long.where(known), df.select("k", "lab"), "k", "lab")
    assert sorted(protos.collect()) == sorted(slow.collect())
    got = langid.nearest_prototype(sparse.where(test), protos, "k", "lab", sim, 40)
    assert sorted(got.collect()) == sorted(langid.nearest_prototype(long.where(test), slow, "k", "lab", sim, 40).collect())
    assert "Exchange" not in got._jdf.queryExecution().executedPlan().toString()  # no row of a bucket is shuffled


def test_neighbour_signature_shuffles_no_token(spark):
    texts = ["The cat sat. the dog, THE cat", "a the a cat", "cat", "", "dog the. sat the cat the", "ÉTÉ the été a"]
    docs = spark.createDataFrame([(i, "en", t) for i, t in enumerate(texts)], "doc_id long, lang string, text string")
    sents = [[t.lower() for t in r["toks"]] for r in postag.sentence_rows(docs).collect()]
    counts = Counter(w for s in sents for w in s)
    top = sorted(counts, key=lambda w: (-counts[w], w))[:3]
    want = {}
    for side in (0, 1):
        near = Counter((s[i + 1 - side], s[i + side]) if side == 0 else (s[i], s[i + 1]) for s in sents for i in range(len(s) - 1))
        for word in counts:
            found = sorted((-n, x) for (w, x), n in near.items() if w == word and x in top)
            want.setdefault(word, []).append(found[0][1] if found else None)
    want = {w: "|".join(x or "-" for x in both) for w, both in want.items() if any(both)}
    got = postag.neighbour_signature(postag.sentence_rows(docs), 3)
    assert {r["word"]: r["cluster"] for r in got.collect()} == want
    assert "Window" not in got._jdf.queryExecution().executedPlan().toString()


def test_stopped_segments_take_no_steps(monkeypatch):
    net = bytespan.ByteSpanNetwork(["A", "B"], 8, 2, seed=4)
    net.bias[net.stop] = 0.3
    texts = [bytes([97 + (i * k) % 26 for k in range(1 + i % 30)]) for i in range(60)]
    alone = [net.write([t])[0] for t in texts]
    steps, step = [], bytespan.ByteSpanNetwork._step
    monkeypatch.setattr(bytespan.ByteSpanNetwork, "_step", lambda self, x, *a: steps.append(len(x)) or step(self, x, *a))
    assert net.write(texts) == alone
    assert len(set(steps)) > 2 and min(steps) < len(texts)
