"""The operators against brute force, and their edge cases: nulls, empty and long texts, ties, repeated rows, empty tables, extra columns."""

import gzip
import hashlib
import random
import re
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from llm_brute import LOW, brute_components
from tinyff.llm import decontaminate, exact_dedup, jaccard, language, licenses, mixing, quality, secrets, toxicity, warc

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def table(spark, texts, extra=False):
    rows = [(i, t, ["en", "de"][i % 2], None if i % 5 == 4 else f"src{i % 3}", 0 if t is None else len(t)) for i, t in enumerate(texts)]
    df = spark.createDataFrame(rows, SCHEMA)
    return df.withColumn("score", F.lit("taken")).withColumn("id", F.lit(1)).withColumn("n", F.lit(2)) if extra else df


EDGES = [None, "", "  \n ", "a", "word", "the same text here", "the same text here", "é ß 漢字 😀 token: abcdefgh12", "x" * 50_000, "long " * 20_000]


def test_exact_dedup(spark):
    texts = EDGES + ["hot"] * 40
    got = {r["doc_id"]: r for r in exact_dedup.exact_dedup(table(spark, texts, True), counters=2).collect()}
    groups = defaultdict(list)
    for i, t in enumerate(texts):
        groups[t or ""].append(i)
    for i, t in enumerate(texts):
        g = groups[t or ""]
        assert (got[i]["keep_id"], got[i]["group_size"], got[i]["kept"]) == (max(g), len(g), i == max(g))
        assert got[i]["text_sha256"] == hashlib.sha256((t or "").encode()).hexdigest()
    assert exact_dedup.exact_dedup(table(spark, EDGES).limit(0)).count() == 0
    kept = exact_dedup.deduplicated(table(spark, texts, True))
    assert kept.count() == len(groups) and "score" in kept.columns


def test_misra_gries_keeps_frequent_digests():
    import pyarrow as pa

    values = [b"a"] * 50 + [bytes([i]) for i in range(60)]
    random.Random(1).shuffle(values)
    batches = [pa.record_batch({"digest": pa.array(values[i : i + 10], pa.binary())}) for i in range(0, len(values), 10)]
    out = next(exact_dedup.misra_gries(3)(iter(batches))).to_pydict()
    assert b"a" in out["digest"] and len(out["digest"]) <= 3


def test_mixing(spark):
    rng = random.Random(3)
    texts = EDGES[:8] + [" ".join("w" for _ in range(rng.randint(0, 60))) for _ in range(200)]
    rows = mixing.mix(table(spark, texts, True)).collect()
    assert len(rows) == len(texts)
    total = sum(r["size"] for r in rows)
    by = defaultdict(list)
    for r in rows:
        assert r["size"] == len(re.findall(r"[^\x20\x09-\x0D]+", texts[r["doc_id"]] or "")) and r["taken"] in (0, r["size"], 2 * r["size"])
        by[None if r["doc_id"] % 5 == 4 else f"src{r['doc_id'] % 3}"].append(r)
    assert sum(g[0]["target"] for g in by.values()) == pytest.approx(1.5 * total)
    for g in by.values():
        assert g[0]["target"] <= 2 * g[0]["source_size"] + 1e-6
        assert abs(sum(r["taken"] for r in g) - g[0]["target"]) <= max(r["size"] for r in g)
    assert mixing.mix(table(spark, EDGES).limit(0)).count() == 0
    assert mixing.mix(table(spark, [None, "", " "])).agg(F.sum("taken")).first()[0] == 0
    mixed = mixing.mixed(table(spark, texts))
    assert mixed.count() == sum(r["copies"] for r in rows)


BASE = {
    "assign": (re.compile(r"""((?i:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.ASCII), lambda m: len(m[2]) >= 8),
    "access": (re.compile(r"AKIA[A-Z0-9]+"), lambda m: len(m[0]) >= 16),
    "hex": (re.compile(r"[0-9a-f]+"), lambda m: len(m[0]) >= 32),
}


def test_secrets(spark, tmp_path):
    texts = EDGES + ["token:secret:abcdefghij PASSWORD = 'hunter22x' ApiKey=\"ab.cd-ef_gh\"", "é AKIA" + "A1" * 8 + " AKIAshort", "0123456789abcdef" * 2 + "g" + "f" * 31, "-----BEGIN RSA PRIVATE KEY-----"] * 2
    got = {r["doc_id"]: r for r in secrets.scan(table(spark, texts, True), str(tmp_path / "ledger")).collect()}
    assert len(got) == len(texts)
    for i, t in enumerate(texts):
        spans = sorted((m.start(), k, list(BASE)[k], m.end()) for k, (rx, ok) in enumerate(BASE.values()) for m in rx.finditer(t or "") if ok(m))
        joined = ",".join(f"{kind}:{a}:{b}" for a, _, kind, b in spans)
        count = Counter(s[2] for s in spans)
        assert (got[i]["n_assign"], got[i]["n_access"], got[i]["n_hex"]) == (count["assign"], count["access"], count["hex"])
        assert got[i]["base_sha256"] == hashlib.sha256(joined.encode()).hexdigest() and set(filter(None, joined.split(","))) <= set(got[i]["spans"].split(","))
    assert "pem:0:31" in got[len(texts) - 1]["spans"]


def test_ledger_is_incremental(spark, tmp_path):
    ledger = str(tmp_path / "ledger")
    secrets.scan(table(spark, ["token=abcdefgh1", "plain"]), ledger).collect()
    before = secrets.ledger_table(spark, ledger, "scanned").count()
    secrets.scan(table(spark, ["token=abcdefgh1", "plain", "token=abcdefgh1"]), ledger).collect()
    assert secrets.ledger_table(spark, ledger, "scanned").count() == before == 2 * len(secrets.RULES)
    newer = (*secrets.RULES, secrets.Rule("word", 1, 9, "plain", base=False))
    got = secrets.scan(table(spark, ["token=abcdefgh1", "plain"]), ledger, newer).collect()
    assert secrets.ledger_table(spark, ledger, "scanned").count() == before + 2
    assert {r["spans"] for r in got} == {"assign:0:15", "word:0:5"}


def brute_windows(text, items, window=13):
    words = lambda s: re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", (s or "").translate(LOW))
    w, hit, found = words(text), set(), set()
    for key, item in items:
        v = words(item)
        k = min(window, len(v))
        for s in range(len(v) - k + 1 if k else 0):
            for p in range(len(w) - k + 1):
                if w[p : p + k] == v[s : s + k]:
                    hit |= set(range(p, p + k))
                    found.add(str(key))
    return len(w), len(hit), sorted(found)


@pytest.mark.parametrize("block", [500_000, 6])
def test_decontamination(spark, block):
    rng = random.Random(5)
    vocab = "alpha beta Gamma δέλτα e5 zeta eta the of".split()
    items = [(i, " ".join(rng.choice(vocab) for _ in range(n))) for i, n in enumerate((20, 13, 5, 1, 15))] + [(9, ""), (10, None), (2, "alpha beta")]
    docs = [" ".join(rng.choice(vocab) for _ in range(40)) + " " + items[k % 3][1].upper() + " tail" for k in range(12)]
    texts = docs + EDGES[:8]
    found = decontaminate.contamination(table(spark, texts, True), spark.createDataFrame(items, "item_id long, text string"), block_windows=block)
    for r in found.collect():
        n, hit, ids = brute_windows(texts[r["doc_id"]], items)
        assert (r["n_words"], r["n_hit"], sorted(r["items"]), r["contaminated"]) == (n, hit, ids, hit > 0 and 20 * hit >= n)
    none = decontaminate.contamination(table(spark, texts), spark.createDataFrame([], "item_id long, text string"))
    assert none.count() == len(texts) and none.where("contaminated").count() == 0


@pytest.mark.parametrize("k,percent", [(4, 85), (5, 80)])
def test_jaccard(spark, k, percent):
    rng = random.Random(7)
    make = lambda n: [f"w{rng.randrange(400)}" for _ in range(n)]
    shared, texts = make(30), list(EDGES)
    for _ in range(6):
        base = make(60)
        for edits in range(8):  # chains of near copies, some of which only link through others
            copy = list(base)
            for _ in range(edits):
                copy[rng.randrange(len(copy))] = f"v{rng.randrange(10**6)}"
            texts.append(" ".join(copy))
            base = copy if edits % 2 else base
    texts += [" ".join(make(40) + shared) for _ in range(20)] + ["one two three", "one two three", "One Two"]
    order = list(range(len(texts)))
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in jaccard.similarity_classes(table(spark, texts, True).repartition(3), k=k, percent=percent).collect()}
    want = brute_components(texts, k, percent)
    assert [got[i] for i in order] == want
    assert jaccard.similarity_classes(table(spark, EDGES).limit(0)).count() == 0


def test_warc_round_trip(spark):
    big = "<html>" + "x" * 200 + "é</html>"
    rows = [(5, "http://a/\nb", big), (3, "http://c", big), (7, None, big), (1, "u", None), (2, "u", "small"), (4, "u", "small"), (None, "u", big), (8, "u", "y" * 300_000), (8, "u", "y" * 300_000)]
    got = warc.round_trip(spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("digest", F.lit("extra")), most=5_000).collect()
    assert len(got) == len(rows)
    for r in got:
        if r["page_id"] in (5, 7, None) and r["payload_bytes"] > 100:
            assert (r["record_type"], r["refers_to"], r["payload_bytes"]) == ("revisit", 3, len(big.encode()))
        else:
            assert (r["record_type"], r["refers_to"]) == ("response", None)
        want = {hashlib.sha256((h or "").encode()).hexdigest() for i, _, h in rows if i == r["page_id"]}
        assert r["payload_digest"] in want
    assert warc.round_trip(spark.createDataFrame([], "page_id long, url string, html string")).count() == 0


def test_normaliser_splits_one_stream_into_members():
    raw = [warc.record(i, f"http://h/{i}", (f"page {i} " * (i * 50)).encode(), "d", None) for i in range(20)]
    whole = gzip.compress(b"".join(raw))
    made = list(warc.normalise_archive(whole, "a" * 32, most=20_000))
    assert len(made) > 1
    back = [r for _, body, lines in made for r in (warc.read_member(body, int(a), int(n)) for _, a, n, *_ in map(str.split, lines))]
    assert back == raw and list(warc.records_of(b"".join(b for _, b, _ in made) + b"\0")) == raw
    assert all(gzip.decompress(body) == b"".join(r for r in raw if r in gzip.decompress(body)) for _, body, _ in made)
    assert all(body[warc.NAME_AT - 1 :][: warc.NAME_CHARS].decode() == name for name, body, _ in made)
    with pytest.raises(ValueError):
        list(warc.records_of(gzip.compress(raw[1][:-10])))


def test_a_damaged_index_is_an_error(spark, tmp_path):
    rows = [(i, f"u{i}", f"page {i} " * 40) for i in range(30)]
    warc.write_monolithic(spark.createDataFrame(rows, "page_id long, url string, html string").coalesce(1), str(tmp_path / "m"))
    warc.normalise(spark, str(tmp_path / "m"), str(tmp_path / "r"), most=2_000)
    index = warc.read_index(spark, str(tmp_path / "r"))
    assert warc.read_records(spark, str(tmp_path / "r")).count() == 30
    some = warc.read_records(spark, str(tmp_path / "r"), F.col("record_id") == "urn:page:7").collect()
    assert [(r["page_id"], r["payload_bytes"]) for r in some] == [(7, len(rows[7][2]))]
    lines = {p: p.read_bytes() for p in (tmp_path / "r" / "kind=index").glob("part-*")}
    for crc in (tmp_path / "r" / "kind=index").glob(".*.crc"):
        crc.unlink()
    assert len(lines) > 2 and index.count() == 30
    path, text = next((p, t) for p, t in sorted(lines.items()) if t.count(b"\n") > 1)
    first, second, *rest = text.split(b"\n")
    wrong_type = second.replace(b" response ", b" revisit ")
    for bad in ([first, *rest], [first, second, *rest][:-1], [first, wrong_type, *rest], []):
        path.write_bytes(b"\n".join(bad))
        with pytest.raises(Exception, match="archive|gzip"):
            warc.read_records(spark, str(tmp_path / "r")).collect()
        path.write_bytes(text)
    assert warc.read_records(spark, str(tmp_path / "r")).count() == 30


def test_licenses(spark):
    rows = [(0, "/a/LICENSE", "Released under the MIT License."), (1, "/a/b/x.txt", "plain words here"), (2, "/a/b/COPYING", "This work is licensed under the GNU General Public License, version 3."), (3, "/a/b/c/y.txt", None), (4, "/z.txt", ""), (5, "/a/w.txt", "text\nLicensed under the Apache License, Version 2.0.\nmore"), (6, None, "nothing")]
    found = licenses.detect(spark.createDataFrame(rows + [(i, f"/q/{i}", f"some other text {i}") for i in range(10, 60)], "doc_id long, path string, text string"), keep=["doc_id", "path"])
    got = {r["doc_id"]: r for r in licenses.inherit(found).collect()}
    assert [got[i]["license"] for i in range(7)] == ["MIT", "GPL-3.0", "GPL-3.0", "GPL-3.0", None, "Apache-2.0", None]
    assert got[1]["inherited_from"] == "/a/b" and got[3]["inherited_from"] == "/a/b" and got[5]["inherited_from"] is None and got[10]["license"] is None
    assert licenses.inherit(found.limit(0)).count() == 0


def test_licenses_do_not_depend_on_table_or_place(spark):
    def own(texts):
        df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
        return [r["own_license"] for r in licenses.detect(df, keep=["doc_id"]).orderBy("doc_id").collect()]

    line = "Code released under the MIT License."
    for rows in (0, 1, 50, 3000):
        assert own([line, *(f"some other text {i}" for i in range(rows))]) == ["MIT"] + [None] * rows
    assert own([f"// Released under the MIT License.\n\nbody {i} of the file" for i in range(40)] + ["no notice"]) == ["MIT"] * 40 + [None]
    wrapped = "# Copyright Someone\n# Licensed under the Apache License, Version 2.0; you may not use\n#\n# this file except in compliance\n# with the License.\ncode = 1"
    long = "word " * 5000 + "\nThis work is licensed under the GNU\nGeneral Public License, version 2.\n" + "end " * 10
    assert own([wrapped, long, "Released under the ISC License.", "you may use this software and the source code of it " * 600, None, ""]) == ["Apache-2.0", "GPL-2.0", None, None, None, None]


def labelled(spark, n=600):
    rng = random.Random(11)
    words = [f"w{i}" for i in range(200)]
    texts, toxic, good = [], [], []
    for i in range(n):
        w = [rng.choice(words) for _ in range(rng.randint(30, 120))]
        if i % 4 == 0:
            for _ in range(6):
                w[rng.randrange(len(w))] = rng.choice(["vile", "rotten", "wretch"])
        junk = i % 3 == 0
        texts.append(" ".join(x.upper() + "!!" if junk else x for x in w))
        toxic.append(int(i % 4 == 0))
        good.append(int(not junk))
    return texts, spark.createDataFrame([(i, g, t) for i, (g, t) in enumerate(zip(good, toxic, strict=True))], "doc_id long, quality int, toxic int")


def test_toxicity_and_quality_learn(spark):
    texts, labels = labelled(spark)
    docs = table(spark, texts + EDGES)
    for op, column in ((toxicity, "toxic"), (quality, "quality")):
        model = op.fit(docs, toxicity.train_labels(labels, column))
        got = op.score(docs, model, keep=["doc_id"]).join(labels, "doc_id", "left").toPandas()
        assert len(got) == len(texts) + len(EDGES) and got["score"].between(0, 1).all()
        known = got[got[column].notna()]
        assert (known["predicted"] == known[column]).mean() > 0.95
        again = op.score(docs, op.fit(docs, toxicity.train_labels(labels, column)), keep=["doc_id"]).toPandas().sort_values("doc_id")
        assert np.allclose(again["score"], got.sort_values("doc_id")["score"])
        none = op.score(table(spark, EDGES, True), op.fit(docs, labels.limit(0), label_col=column))
        assert none.count() == len(EDGES) and none.agg(F.max("score")).first()[0] == 0


def test_toxicity_of_fixed_pairs(spark):
    """The words b and c always follow one word; only the pair tells the classes apart."""
    rng = random.Random(13)
    texts = []
    for i in range(800):
        w = [f"w{rng.randrange(60)}" for _ in range(rng.randint(20, 60))]
        for _ in range(3):
            w.insert(rng.randrange(len(w) + 1), "x b y c" if i % 2 else "x c y b")
        texts.append(" ".join(w))
    labels = spark.createDataFrame([(i, i % 2) for i in range(len(texts))], "doc_id long, toxic int")
    docs = table(spark, texts)
    model = toxicity.fit(docs, toxicity.train_labels(labels))
    got = toxicity.score(docs, model, keep=["doc_id"]).toPandas()
    assert (got["predicted"] == got["doc_id"] % 2).mean() > 0.95
    plain = spark.createDataFrame([(0, "w1 x b w2"), (1, "w1 x c w2")], "doc_id long, text string")
    toxic, ordinary = (r["score"] for r in toxicity.score(plain, model).orderBy("doc_id").collect())
    assert toxic > 0.5 > ordinary


def test_language(spark):
    rng = random.Random(2)
    parts = {"en": ["the", "of", "ing", "th"], "de": ["der", "sch", "ung", "ich"]}
    rows = [(i, " ".join(rng.choice(parts[lang]) + rng.choice("aeiou") for _ in range(30)), lang) for i in range(200) for lang in [("en", "de")[i % 2]]]
    docs = spark.createDataFrame(rows + [(1000 + i, t, None) for i, t in enumerate(EDGES + ["123 !!"])], "doc_id long, text string, lang string")
    got = {r["doc_id"]: r for r in language.score(docs, language.fit(docs, docs), keep=["doc_id"]).collect()}
    assert np.mean([got[i]["lang_pred"] == lang for i, _, lang in rows]) > 0.98
    assert all(got[1000 + i]["lang_pred"] == "und" and got[1000 + i]["score"] == 0 for i in (0, 1, 2, len(EDGES)))
    assert all(0 <= r["score"] <= 1 for r in got.values())
    assert {r["lang_pred"] for r in language.score(docs, language.fit(docs, docs.limit(0))).collect()} == {"und"}


def test_cell_product():
    """Overlaps of wanted entries against sets, with rows given twice and slices of every width."""
    rng = np.random.default_rng(4)
    for case in range(30):
        sets = [np.unique(rng.integers(0, 60, rng.integers(1, 80)).astype(np.uint64)) for _ in range(25)]
        ids = rng.permutation(1000)[:25].astype(np.int64)
        x, y = rng.integers(0, 25, (2, 120))
        x, y = x[x != y], y[x != y]
        got = jaccard.cell_product(np.append(ids, ids[:3]), sets + sets[:3], ids[x], ids[y], 50 + case)
        want = [100 * (n := len(np.intersect1d(sets[i], sets[j]))) >= (50 + case) * (len(sets[i]) + len(sets[j]) - n) for i, j in zip(x, y, strict=True)]
        assert got.tolist() == want


def test_jaccard_keeps_large_ids_beside_null_ones(spark):
    big = 2**53 + 1
    rows = [(big, "a b c d e f g h"), (None, "something else entirely here now"), (big + 1, "a b c d e f g h"), (big + 2, " ".join(f"w{i}" for i in range(40))), (big + 3, " ".join(f"w{i}" for i in range(39)))]
    got = jaccard.similarity_classes(spark.createDataFrame(rows, "doc_id long, text string").coalesce(1)).collect()
    assert {(r["doc_id"], r["component_id"]) for r in got} == {(big, big), (None, None), (big + 1, big), (big + 2, big + 2), (big + 3, big + 2)}
