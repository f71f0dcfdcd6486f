"""Canonical forms, licenses, language models, the toxicity grammar and near duplicates against independent brute force, and odd inputs."""

from __future__ import annotations

import hashlib
import math
import random
import re
import unicodedata
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from unionlake.llm import common, covering, fingerprint, langid, license_scan, near_dedup, toxicity, warc

SMALL, LARGER = "/root/testdata/sf0.001", "/root/testdata/sf0.01"


def test_canonical_text_equals_the_unicode_database(spark):
    rng = random.Random(0)
    # one letter of many scripts, compatibility forms, marks, blanks; all long assigned
    pool = "aZéÉßſẞŒıİΣσςΑΩЯйЁאبतक한ㄱ한ﬁﬀ①Ⅳ㎏ｱア゙ªº½²K\u212bÅ\u0301\u0327\u0308\u00a0\u2003\u3000 \t\n\x0b\x85.,!-_0９"
    texts = ["".join(rng.choice(pool) for _ in range(rng.randint(0, 40))) for _ in range(600)] + [None, "", "  ", "\ufeffx\u200b y"]

    def canonical(t):
        t = unicodedata.normalize("NFKC", unicodedata.normalize("NFKC", t or "").casefold())
        return re.sub("[\\s\u200b\ufeff\x1c-\x1f\x85]+", " ", t).strip(" ")

    rows = spark.createDataFrame(list(enumerate(texts)), "i int, text string").select("i", fingerprint.canonical_text(F.col("text")).alias("c")).collect()
    assert {r["i"]: r["c"] for r in rows} == {i: canonical(t) for i, t in enumerate(texts)}
    by = defaultdict(set)
    for r in fingerprint.fingerprints(spark.createDataFrame(list(enumerate(texts)), "doc_id int, text string")).collect():
        by[r["fingerprint"]].add(canonical(texts[r["doc_id"]]))
    assert all(len(x) == 1 for x in by.values()) and len(by) == len({canonical(t) for t in texts})


def words_of(text):
    return re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", (text or "").translate({c: c + 32 for c in range(65, 91)}))


def base_places(text):
    w, out = words_of(text), []
    for phrase, label in license_scan.BASE:
        p = phrase.split()
        out += [(i, label) for i in range(len(w) - len(p) + 1) if w[i : i + len(p)] == p]
    return len(w), out


def check_licenses(spark, docs):
    rows = docs.select("doc_id", "text").collect()
    want = Counter()
    for r in rows:
        n, places = base_places(r["text"])
        at = [i for i, _ in places]
        want[r["doc_id"], n, len(places), min(at, default=None), max(at, default=None), ",".join(sorted({x for _, x in places}))] += 1
    got = license_scan.scan(spark, docs).collect()
    assert Counter((g["doc_id"], g["n_words"], g["n_base"], g["first_word"], g["last_word"], g["base_labels"]) for g in got) == want
    for g in got:
        assert 0.0 <= g["score"] <= 1.0 and set(filter(None, g["base_labels"].split(","))) <= set(g["labels"].split(","))
    return got


def test_base_licenses(spark):
    assert sum(g["n_base"] for g in check_licenses(spark, common.table(spark, LARGER, "documents"))) > 0
    rng = random.Random(6)
    pool = ["under", "the", "MIT", "license", "cc", "by", "nc", "Apache", "version", "2", "x", ".", "é"]
    rows = [(i % 300, " ".join(rng.choice(pool) for _ in range(rng.randint(0, 60))), 1, 2) for i in range(400)]
    rows += [(None, "cc by nc", 1, 2), (1000, None, 1, 2), (1001, "cc-by-nc " * 30_000, 1, 2), (1002, "", 1, 2)]
    odd = spark.createDataFrame(rows, "doc_id bigint, text string, row_id int, n_words int")
    check_licenses(spark, odd)
    assert check_licenses(spark, odd.where("false")) == []


def test_license_wordings_stand_in_order(spark):
    phrase, label, _ = license_scan.WORDINGS[1]
    w = phrase.split()
    rng = random.Random(7)
    shuffled = rng.sample(w, len(w))
    texts = [phrase, "x " * 50 + phrase.upper() + " y" * 50, " ".join([*w[:6], "really", *w[6:]]), " ".join([*w[:5], *w[6:]]), " ".join(w[:-4]), " ".join(shuffled), " ".join(w[:4]), "no license at all"]
    got = {r["doc_id"]: r for r in license_scan.scan(spark, spark.createDataFrame(list(enumerate(texts)), "doc_id int, text string")).collect()}
    assert [got[i]["labels"] for i in range(8)] == [label] * 5 + ["", "", ""]
    assert got[0]["score"] == got[1]["score"] == 1.0 > got[2]["score"] > 0.6

    def common_words(a, b):
        best = [0] * (len(b) + 1)
        for x in a:
            corner = 0
            for j, y in enumerate(b):
                corner, best[j + 1] = best[j + 1], corner + 1 if x == y else max(best[j + 1], best[j])
        return best[-1]

    for _ in range(2000):
        a, b = ([rng.randint(1, 5) for _ in range(rng.randint(0, 12))] for _ in range(2))
        assert license_scan.common_length(a, b) == common_words(a, b)


def kneser_ney(sequences, order, size, discount=0.75):
    """p(code, codes before it), from the definition, with dictionaries."""
    grams = [Counter() for _ in range(order + 1)]
    for s in sequences:
        for i in range(order - 1, len(s)):
            grams[order][tuple(s[i - order + 1 : i + 1])] += 1
    for k in range(order - 1, 0, -1):
        left = defaultdict(set)
        for g in grams[k + 1]:
            left[g[1:]].add(g[0])
        grams[k] = Counter({g: len(x) for g, x in left.items()})
    followers = [defaultdict(dict) for _ in range(order + 1)]
    for k in range(1, order + 1):
        for g, n in grams[k].items():
            followers[k][g[:-1]][g[-1]] = n

    def p(code, before):
        if len(before) + 1 == 0:
            return 1.0 / size
        below = p(code, before[1:]) if before else 1.0 / size
        own = followers[len(before) + 1].get(tuple(before))
        if not own:
            return below
        total = sum(own.values())
        return max(own.get(code, 0) - discount, 0) / total + discount * len(own) / total * below

    return p


@pytest.mark.parametrize("order", [1, 2, 3])
def test_kneser_ney(order):
    rng = random.Random(8)
    letters = list("abcd")
    alphabet = langid.Alphabet(letters)
    training = [["".join(rng.choice(pool) for _ in range(rng.randint(1, 30))) for _ in range(12)] for pool in ("aab c", "bcd d.")]
    counts, models = [], []
    for texts in training:
        codes, begins = alphabet.codes(texts, order - 1)
        counts.append(np.unique(langid.runs(codes, begins, order, alphabet.size)[0], return_counts=True))
        ends = [*begins[1:], len(codes)]
        models.append(kneser_ney([codes[a:b].tolist() for a, b in zip(begins, ends, strict=True)], order, alphabet.size))
    m = langid.Models(["one", "two"], letters, counts, order)
    texts = ["abc", "d", "zzz aab", "bca  dd. a", "caab"]
    h, n = m.cross_entropies(texts)
    codes, begins = alphabet.codes(texts, order - 1)
    for i, (a, b) in enumerate(zip(begins, [*begins[1:], len(codes)], strict=True)):
        s = codes[a:b].tolist()
        places = range(order - 1, len(s))
        assert n[i] == len(places)
        for lang in range(2):
            want = -sum(math.log(models[lang](s[j], s[j - order + 1 : j])) for j in places) / len(places)
            assert h[i, lang] == pytest.approx(want, rel=1e-4)


def test_texts_of_a_language_left_out_are_rejected(spark):
    docs = common.table(spark, LARGER, "documents").where("length(text) >= 200")
    for left_out in ("de",):
        rows = langid.predict(spark, docs, langid.train(spark, docs.where(F.col("lang") != left_out)), F.lit(False)).select("doc_id", "rejected")
        per = {r["foreign"]: r["share"] for r in docs.join(rows, "doc_id").groupBy((F.col("lang") == left_out).alias("foreign")).agg(F.avg(F.col("rejected").cast("int")).alias("share")).collect()}
        assert per[True] > 0.95 and per[False] < 0.002
    every = common.table(spark, LARGER, "documents")
    assert langid.accept(spark, every).count() >= 0.999 * every.count()


def matched(words, kinds, scope=3):
    """The output symbols of a clause, from what the grammar means, word by word."""
    k = [kinds.get(w, "O") for w in words]
    out = list(k)
    for i, x in enumerate(k):
        if x not in "IT":
            continue
        mark = x
        if "R" in k[:i]:
            mark = {"I": "i", "T": "t"}[mark]
        if mark in "IT" and "N" in k[max(0, i - scope) : i]:
            mark = {"I": "j", "T": "u"}[mark]
        if mark in "IT" and ("Y" in k[max(0, i - scope) : i] or "Y" in k[i + 1 : i + 1 + scope]):
            mark = {"I": "A", "T": "B"}[mark]
        out[i] = mark
    return out


def test_the_grammar_means_what_it_says():
    rng = random.Random(9)
    kinds = {"fool": "I", "hurt": "T", "you": "Y", "not": "N", "says": "R"}
    s = toxicity.Scorer({w: (c, 2.0) for w, c in kinds.items()}, {}, dict(toxicity.FACTORS))
    for _ in range(4000):
        words = [rng.choice([*kinds, "some", "word"]) for _ in range(rng.randint(0, 9))]
        best = max((toxicity.FACTORS[y] for y in matched(words, kinds) if y in toxicity.FACTORS), default=None)
        got = s.clauses(" ".join(words))
        assert [toxicity.FACTORS[p] for p, _ in got] == ([] if best is None else [best])


def test_components_with_salts(spark):
    rng = random.Random(10)
    edges = {(min(a, b), max(a, b)) for a, b in ((rng.randrange(300), rng.randrange(300)) for _ in range(170)) if a != b} | {(0, i) for i in range(400, 500)}
    root = {i: i for e in edges for i in e}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for a, b in edges:
        x, y = find(a), find(b)
        root[max(x, y)] = min(x, y)
    df = spark.createDataFrame(sorted(edges), "a bigint, b bigint")
    names = spark.createDataFrame([(i, i) for i in range(600)], "node bigint, name bigint")
    for limit in (0, 10_000):
        got = covering.components(spark, df, names, broadcast_nodes=limit, salts=3)
        assert {r["node"]: r["root"] for r in got.collect()} == {i: find(i) for i in root}


def test_no_near_copy_of_the_given_documents_stays(spark):
    """Recall against every pair that shares a shingle: all of them meet."""
    docs = common.table(spark, LARGER, "documents")
    sets = {r["doc_id"]: frozenset(covering.shingle_hashes(covering.words_of(r["text"]), 5)) for r in docs.collect()}
    holders = defaultdict(list)
    for i in sorted(sets):
        for h in sets[i]:
            holders[h].append(i)
    shared = Counter((a, b) for ids in holders.values() if len(ids) < 400 for n, a in enumerate(ids) for b in ids[n + 1 :])
    pairs = [(a, b) for (a, b), n in shared.items() if len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b])]
    assert len(pairs) > 50
    root = {i: i for i in sets}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for a, b in pairs:
        x, y = find(a), find(b)
        root[max(x, y)] = min(x, y)
    kept = {r["doc_id"] for r in near_dedup.keep_first(spark, docs).collect()}
    assert kept == {find(i) for i in sets}


def test_urls_cannot_forge_headers(spark):
    html = "<p>" + "y" * 1200
    urls = ["http://x/a\r\nb", "http://x/a\r\nWARC-Type: revisit", "http://x/ü ü\t%20", "", None, "x" * 5000]
    pages = spark.createDataFrame([(i, u, html + str(i)) for i, u in enumerate(urls)], "page_id bigint, url string, html string")
    got = {r["page_id"]: r for r in warc.round_trip(spark, pages).collect()}
    assert len(got) == len(urls)
    for i in range(len(urls)):
        assert (got[i]["record_type"], got[i]["payload_digest"]) == ("response", hashlib.sha1((html + str(i)).encode()).hexdigest())


def test_pipeline_on_odd_rows(spark, tmp_path):
    for name in ("labels", "benchmark"):
        common.table(spark, SMALL, name).write.parquet(str(tmp_path / f"{name}.parquet"))
    docs = common.table(spark, SMALL, "documents")
    text = docs.where("lang = 'en' and length(text) > 500").first()["text"]
    odd = [(None, text + " and no id", "en", "s", 1), (900_001, None, None, None, None), (900_002, "", "en", "s", 0), (900_003, text, None, "s", 1), (900_003, text, None, "s", 1), (900_004, " ".join(random.Random(11).choices(text.split(), k=60_000)), "en", None, 2)]
    every = docs.unionByName(spark.createDataFrame(odd, docs.schema)).withColumns({c: F.lit(7) for c in ("score", "_key", "group_key", "fp", "row_id", "rejected")})
    for rows in (every, every.where("false")):
        cur = rows
        for name, stage in corpus_pipeline.STAGES[:-1]:
            cur = common.checkpointed(spark, stage(spark, cur, str(tmp_path)), "odd")
            assert cur.columns == rows.columns, name
        packed = corpus_pipeline.STAGES[-1][1](spark, cur, str(tmp_path)).toPandas()
        kept = [r["doc_id"] for r in cur.select("doc_id").collect()]
        assert set(packed.doc_id.dropna()) == {i for i in kept if i is not None}
        assert not {900_001, 900_002, 900_003} & set(kept)  # no letter, or a copy
        if rows is every:
            assert {900_004, None} <= set(kept)
