"""The trained operators and the licence scan against plain Python versions, and their edge cases."""

import math
import random
import re
from bisect import bisect_right
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from test_operators import EDGES, labelled, table
from tinyff.llm import decontaminate, language, licenses, quality, queries, rows, toxicity

WORDS = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")


def low(text):
    return re.sub("[A-Z]", lambda m: m[0].lower(), text or "")


def test_log_likelihood_ratios(spark):
    """Both class models by counting in dictionaries."""
    rng = random.Random(5)
    texts = [" ".join(rng.choice("a b c d e f g h i j k l m".split()) if rng.random() < 0.9 else "vile scum"[5 * (i % 2) :] for _ in range(rng.randint(1, 40))) for i in range(400)] + EDGES
    labels = spark.createDataFrame([(i, None, i % 2) for i in range(400)] + [(400, None, None), (None, None, 1)], "doc_id long, quality int, toxic int")
    docs = table(spark, texts)
    model = toxicity.fit(docs, toxicity.train_labels(labels), per_class=10**6)
    sample = [r for r in rows.label_sample(toxicity.train_labels(labels), "doc_id", "toxic", 10**6)[0].collect() if r["draw"] < toxicity.MODEL_SHARE]
    pairs = [Counter(), Counter()]
    for r in sample:
        w = WORDS.findall(low(texts[r["id"]]))
        pairs[r["label"]].update(zip(["", *w], w, strict=False))
    shared = Counter(w for t in texts for w in WORDS.findall(low(t)))
    cut = lambda n: min(n, toxicity.Z * math.sqrt(n))
    cont = [Counter(w for _, w in p) for p in pairs]
    held = {w for c in cont for w, n in c.items() if n > 4} | {x for p in pairs for pair, n in p.items() if n > 4 for x in pair}
    total = sum(shared.values())

    def backoff(c, w):
        k, d = sum(cont[c].values()), sum(map(cut, cont[c].values()))
        n = cont[c][w]
        return (n - cut(n)) / (k + 1) + (d + 1) / (k + 1) * (shared[w] + 0.5) / (total + 0.5 * (len(held) + 1))

    def chance(c, h, w):
        after = {x: n for (y, x), n in pairs[c].items() if y == h}
        n = sum(after.values())
        if not n:
            return backoff(c, w)
        return (after.get(w, 0) - cut(after.get(w, 0))) / n + max(sum(map(cut, after.values())) / n, 1e-3) * backoff(c, w)

    def known_context(h):
        return h in held and any(sum(n for (y, _), n in pairs[c].items() if y == h) > 4 for c in (0, 1))

    def ratio(h, w):
        if w not in held:
            base = math.log((sum(map(cut, cont[1].values())) + 1) / (sum(cont[1].values()) + 1) / ((sum(map(cut, cont[0].values())) + 1) / (sum(cont[0].values()) + 1)))
            w = None
        if any(p[h, w] > 4 for p in pairs) and w is not None:
            return math.log(chance(1, h, w) / chance(0, h, w))
        value = base if w is None else math.log(backoff(1, w) / backoff(0, w))
        if known_context(h):
            weight = [max(sum(cut(n) for (y, _), n in pairs[c].items() if y == h) / max(1, sum(n for (y, _), n in pairs[c].items() if y == h)), 1e-3) if any(y == h for y, _ in pairs[c]) else 1.0 for c in (0, 1)]
            value += math.log(weight[1] / weight[0])
        return value

    run = toxicity._ratios(model)()
    for t in [x for x in texts if len(x or "") < 300][::5]:
        raw = np.frombuffer((t or "").encode(), np.uint8)
        got, w = run(raw, np.array([0, len(raw)])), WORDS.findall(low(t))
        want = [ratio(h, x) for h, x in zip(["", *w], w, strict=False)]
        assert got["mean"][0] == pytest.approx(sum(want) / max(len(want), 1), abs=1e-9)
        assert got["over0"][0] == sum(x > toxicity.MARKS[0] for x in want)
        assert got["excess1"][0] == pytest.approx(sum(max(x - toxicity.MARKS[1], 0) for x in want) / max(len(want), 1), abs=1e-9)


def test_quality_by_hand(spark):
    """Features, bins and sums of table entries, one text at a time."""
    texts, labels = labelled(spark, 300)
    texts = texts + EDGES + ["Line one.\nLine one.\n\nThree, 45 words! é\t#$"]
    model = quality.fit(table(spark, texts), toxicity.train_labels(labels, "quality"))
    got = {r["doc_id"]: r["score"] for r in quality.score(table(spark, texts), model, keep=["doc_id"]).collect()}
    for i, t in enumerate(texts):
        raw = (t or "").encode()
        words = re.findall(rb"[^ \t\n\x0b\x0c\r]+", raw.lower())  # ASCII capitals alone are folded in bytes
        lines = re.findall(rb"[^\n]+", raw)
        share = lambda x, n: x / n if n else 0.0
        kinds = [share(sum(b in set(v) for b in raw), len(raw)) for v in quality._CLASSES.values()]
        x = [math.log1p(len(raw)), math.log1p(len(words)), share(sum(map(len, words)), len(words)), *kinds, share(len(set(words)), len(words)), share(len(set(lines)), len(lines)), share(sum(len(w) <= 3 for w in words), len(words)), share(sum(len(w) > 16 for w in words), len(words)), len(words) / max(len(lines), 1)]
        at = [bisect_right(list(c), v) for c, v in zip(model.cuts, x, strict=True)]
        z = model.base + sum(model.single[j][b] for j, b in enumerate(at))
        z += sum(t2[model.coarse[a][at[a]]][model.coarse[b][at[b]]] for (a, b), t2 in zip(model.pairs, model.pair_tables, strict=True))
        assert got[i] == pytest.approx(1 / (1 + math.exp(-max(-30, min(30, z)))), abs=1e-6)


def test_tree_takes_the_best_split():
    rng = np.random.default_rng(1)
    for _ in range(20):
        g, h = rng.normal(size=8), rng.uniform(0.1, 1, 8)
        worth = lambda a, b: g[a:b].sum() ** 2 / (h[a:b].sum() + 5.0)
        best = max(range(1, 8), key=lambda c: worth(0, c) + worth(c, 8))
        step = quality._splits(g, h, 2, 5.0)
        if worth(0, best) + worth(best, 8) <= worth(0, 8) + 1e-9:  # no split is worth it
            assert step == pytest.approx(-g.sum() / (h.sum() + 5))
            continue
        assert step[:best] == pytest.approx(-g[:best].sum() / (h[:best].sum() + 5)) and step[best:] == pytest.approx(-g[best:].sum() / (h[best:].sum() + 5))


def hand_slots(text):
    mask, found = (1 << 64) - 1, Counter()
    for n in language.ORDERS:
        for i in range(len(text) - n + 1):
            run = 0
            for c in text[i : i + n]:
                run = (run * 0x100000001B3 + ord(c) + 1) & mask
            x = (run + (n << 56)) & mask
            x = ((x ^ (x >> 32)) * 0xD6E8FEB86659FD93) & mask
            x = ((x ^ (x >> 29)) * 0xA3B195354A39B70D) & mask
            found[(x ^ (x >> 32)) & (language.SLOTS - 1)] += 1
    return found


def test_language_by_hand(spark):
    """Document frequencies, vectors and probabilities, one text at a time; held-out texts change nothing."""
    rng = random.Random(3)
    parts = {"en": "the of and ing".split(), "de": "der sch ung ich".split(), "fr": "les eau des tion".split()}
    data = [(i, " ".join(rng.choice(parts[lang]) + rng.choice("aeiou") for _ in range(rng.randint(1, 25))), lang) for i in range(300) for lang in [rng.choice(list(parts))]]
    data += [(1000 + i, t, None) for i, t in enumerate([*EDGES, "123", "İstanbul ΣΑΣ"])]
    docs = spark.createDataFrame(data, "doc_id long, text string, lang string")
    learn = docs.where(rows.fold_of(F.col("doc_id")) != 0)
    model = language.fit(learn, learn)
    seen = Counter()
    texts = [r["text"] for r in learn.collect() if r["text"]]
    for t in texts:
        seen.update(set(hand_slots(t.lower())))
    idf = [math.log((1 + len(texts)) / (1 + seen[s])) + 1 for s in range(language.SLOTS)]
    assert np.allclose(model.idf, idf, atol=1e-5)
    got = {r["doc_id"]: r for r in language.score(docs, model, keep=["doc_id"]).collect()}
    for i, t, _ in data:
        if not t or not any(map(str.isalpha, t)):
            assert (got[i]["lang_pred"], got[i]["score"]) == ("und", 0.0)
            continue
        v = {s: (1 + math.log(n)) * idf[s] for s, n in hand_slots(t.lower()).items()}
        norm = math.sqrt(sum(x * x for x in v.values()))
        z = [sum(x / norm * float(model.weights[s][k]) for s, x in v.items()) / model.temperature for k in range(3)]
        p = [math.exp(x - max(z)) for x in z]
        assert got[i]["score"] == pytest.approx(max(p) / sum(p), abs=1e-4) and got[i]["lang_pred"] == model.languages[int(np.argmax(p))]
    changed = docs.withColumn("text", F.when(rows.fold_of(F.col("doc_id")) == 0, F.lit("zzz qqq www")).otherwise(F.col("text")))
    learn = changed.where(rows.fold_of(F.col("doc_id")) != 0)
    again = language.fit(learn, learn)
    assert (again.idf == model.idf).all() and (again.weights == model.weights).all() and again.temperature == model.temperature


def test_language_query_learns_from_rows_that_are_not_held_out(spark, tmp_path):
    docs = spark.createDataFrame([(i, "der die das" if i % 2 else "the of and", "de" if i % 2 else "en", "s", 1) for i in range(60)], "doc_id long, text string, lang string, source string, n_chars long")
    scores = []
    for k in range(2):
        held = rows.fold_of(F.col("doc_id")) == 0
        docs.withColumn("text", F.when(held & F.lit(k == 1), F.lit("xx yy zz")).otherwise(F.col("text"))).write.parquet(str(tmp_path / str(k) / "documents.parquet"))
        scores.append({r["doc_id"]: r["score"] for r in queries.op6_language(spark, str(tmp_path / str(k))).where("NOT held_out").collect()})
    assert scores[0] == scores[1] and len(scores[0]) > 30


def hand_terms(text):
    w = WORDS.findall(low(text))
    return Counter(w) + Counter(zip(w, w[1:], strict=False)), len(w)


def test_licences_by_hand(spark):
    """Cosines of every line, block of lines and text, by dictionaries."""
    rng = random.Random(8)
    notices = [t for v in licenses.TEMPLATES.values() for t in v]
    texts = [None, "", "\n\n"]
    for _ in range(60):
        lines = [" ".join(rng.choice("the a file license under of code public version mit".split()) for _ in range(rng.randint(0, 9))) for _ in range(rng.randint(1, 6))]
        if rng.random() < 0.5:
            words = rng.choice(notices).split()
            cut = rng.randint(1, len(words))
            lines[rng.randrange(len(lines)) : 0] = [" ".join(words[:cut]), " ".join(words[cut:])] * rng.randint(1, 2)
        texts.append("\n".join(lines))
    templates = [(name, hand_terms(t)[0]) for name in sorted(licenses.TEMPLATES) for t in licenses.TEMPLATES[name]]
    known = set().union(*[t for _, t in templates])
    seen = Counter(x for t in texts for x in hand_terms(t)[0].keys() & known)
    idf = {x: math.log((1 + len(texts)) / (1 + seen[x])) + 1e-3 for x in known}

    def cosine(words, template):
        terms = Counter(words) + Counter(zip(words, words[1:], strict=False))
        own = {x: n for x, n in terms.items() if x in known}
        if not own:
            return 0.0
        outside = sum(terms.values()) - sum(own.values())
        square = sum((n * idf[x]) ** 2 for x, n in own.items()) + outside * sum(n * idf[x] ** 2 for x, n in own.items()) / sum(own.values())
        return sum(n * idf[x] * template.get(x, 0) * idf[x] for x, n in own.items()) / math.sqrt(square) / math.sqrt(sum((n * idf[x]) ** 2 for x, n in template.items()))

    docs = table(spark, texts + [texts[5]], True).withColumn("own_score", F.lit("taken"))
    got = {r["doc_id"]: r for r in licenses.detect(table(spark, texts), keep=["doc_id"]).collect()}
    for i, t in enumerate(texts):
        lines = [w for w in (WORDS.findall(low(x)) for x in (t or "").split("\n")) if w]
        units = [sum(lines[a : a + n], []) for n in range(1, licenses.BLOCK_LINES + 1) for a in range(len(lines))] + [WORDS.findall(low(t))]
        best = max(cosine(u, template) for u in units for _, template in templates) if lines else 0.0
        assert got[i]["own_score"] == pytest.approx(best, abs=1e-9)
        names = {name for u in units for name, template in templates if abs(cosine(u, template) - best) < 1e-9}
        assert got[i]["own_license"] in names if best >= licenses.THRESHOLD else got[i]["own_license"] is None
    more = licenses.detect(docs, threshold=0.7)
    assert more.count() == len(texts) + 1 and dict(more.dtypes)["own_score"] == "double"


@pytest.mark.parametrize("op,column", [(toxicity, "toxic"), (quality, "quality")])
def test_labels_and_ids_of_every_kind(spark, op, column):
    texts, labels = labelled(spark, 200)
    more = spark.createDataFrame([(None, 1, 1), (3, None, None), (4, 1, 1), (4, 0, 0), (10**9, 1, 1)], "doc_id long, quality int, toxic int")
    docs = table(spark, texts, True).withColumn("predicted", F.lit("taken"))
    repeated = docs.unionByName(docs.limit(20)).unionByName(docs.limit(5).withColumn("text", F.lit(None).cast("string"))).unionByName(docs.limit(3).withColumn("doc_id", F.lit(None).cast("long")))
    model = op.fit(repeated, toxicity.train_labels(labels.unionByName(more), column))
    got = op.score(repeated, model)
    assert got.count() == 228 and set(got.columns) == set(docs.columns) | {"score", "predicted"} and dict(got.dtypes)["predicted"] == "int"
    assert op.score(repeated.limit(0), model).count() == 0 == op.score(repeated, op.fit(repeated.limit(0), labels, label_col=column)).where("score > 1").count()


def test_language_rows_of_every_kind(spark):
    docs = spark.createDataFrame([(None if i % 3 == 0 else i % 5, ("der " if i % 2 else "the ") * (i % 7 + 1), "de" if i % 2 else "en") for i in range(100)], "doc_id long, text string, lang string").withColumn("score", F.lit("x")).withColumn("label", F.lit("y"))
    got = language.score(docs, language.fit(docs, docs))
    assert got.count() == 100 and got.where("lang_pred = lang").count() == 100 and dict(got.dtypes)["score"] == "double"
    assert language.score(docs.limit(0), language.fit(docs.limit(0), docs.limit(0))).count() == 0


def test_contamination_does_not_depend_on_blocks(spark):
    """Repeated and null ids, kept columns, and items without an id, for one block and for several."""
    items = [(1, "alpha beta gamma delta"), (None, "one two three"), (None, "beta gamma"), (1, "zeta"), (7, "x " * 30)]
    bench = spark.createDataFrame(items, "item_id long, text string")
    texts = ["alpha beta gamma delta zeta", "one two three four", "nothing here", None, "", "x " * 100, "alpha beta gamma delta zeta"]
    docs = spark.createDataFrame([(i, t, f"n{k}", k) for i in (5, None) for k, t in enumerate(texts)], "doc_id long, text string, items string, mark long")
    seen = set()
    for block in (500_000, 20, 3, 1):
        got = decontaminate.contamination(docs, bench, block_windows=block, keep=["doc_id", "mark", "text"])
        assert got.columns[:3] == ["doc_id", "mark", "text"]
        rows_ = sorted(((r["doc_id"] or -1, r["mark"], r["n_words"], r["n_hit"], tuple(x or "~" for x in r["items"]), r["contaminated"]) for r in got.collect()))
        assert len(rows_) == 14
        seen.add(tuple(rows_))
    assert len(seen) == 1
    one = {r[1]: r[2:] for r in next(iter(seen)) if r[0] == 5}
    assert one[0] == (5, 5, ("1", "~"), True) and one[1] == (4, 3, ("~",), True) and one[2] == (2, 0, (), False) and one[3] == one[4] == (0, 0, (), False) and one[5] == (100, 100, ("7",), True)
    digest = spark.createDataFrame([(["1", None],)], "i array<string>").select(decontaminate.item_digest(F.col("i"))).first()[0]
    assert digest == spark.createDataFrame([(["1"],)], "i array<string>").select(decontaminate.item_digest(F.col("i"))).first()[0]


def test_toxic_texts_of_any_length_are_found(spark):
    """Held-out texts: the rule of one half must find most of the toxic ones, long ones too, and leave the others alone."""
    d = "/root/testdata/sf0.1"
    docs, labels = (spark.read.parquet(f"{d}/{t}.parquet") for t in ("documents", "labels"))
    model = toxicity.fit(docs, toxicity.train_labels(labels))
    held = docs.join(labels.where((rows.fold_of(F.col("doc_id")) == 0) & F.col("toxic").isNotNull()), "doc_id")
    share = {r["toxic"]: r["s"] for r in toxicity.score(held, model, keep=["toxic"]).groupBy("toxic").agg(F.avg("predicted").alias("s")).collect()}
    assert share[1] > 0.77 and share[0] < 0.02
