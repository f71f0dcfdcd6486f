"""Language models, tokens, packing, toxicity and license scans against brute force on small fixtures."""

from __future__ import annotations

import hashlib
import io
import math
import random
import struct
import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest
import xxhash
import zstandard

from unionlake.llm import common, fingerprint, langid, license_scan, packing, ppm, token_store, tokens, toxicity

SF = "/root/testdata/sf0.001"
ODD = [(1, "Café  Au LAIT", "x"), (2, "café au lait", "y"), (3, None, "z"), (4, "", None), (None, "no id", "q"), (5, "dup", "a"), (5, "dup", "a"), (6, "word " * 30_000, "long"), (7, "ﬁn ΣΑΣ <|endoftext|> naïve 日本 😀", "u")]


@pytest.fixture(scope="module")
def odd(spark):
    return spark.createDataFrame([(i, t, x, 9) for i, t, x in ODD], "doc_id bigint, text string, fingerprint string, n_words int")


@pytest.fixture(scope="module")
def docs(spark):
    return common.table(spark, SF, "documents")


def test_fingerprints(spark, odd):
    r = {(x["doc_id"], x["n_chars"]): x for x in fingerprint.edited_report(spark, odd).collect()}
    assert len(r) == len({(i, len(t or "")) for i, t, _ in ODD})
    one, two = r[1, 13], r[2, 12]
    assert one["fingerprint"] == two["fingerprint"] and one["class_id"] == two["class_id"] == 1
    assert r[3, 0]["fingerprint"] == r[4, 0]["fingerprint"] and r[4, 0]["near_next"] == 1.0
    order = sorted((t for t in ODD if t[0] is not None), key=lambda t: -t[0]) + [(None, "no id", "q")]
    texts = [t or "" for _, t, _ in order]
    for k, (i, t, _) in enumerate(order):
        t, nxt = t or "", texts[(k + 1) % len(texts)]
        m = len(t) // 3
        if i == 5:  # two rows under one key here
            continue
        assert r[i, len(t)]["edited_sha256"] == hashlib.sha256((t[: len(t) - m] + nxt[:m]).encode()).hexdigest()
    assert fingerprint.edited_report(spark, odd.where("false")).count() == 0


def test_next_document_over_many_buckets(spark, docs):
    r = fingerprint.with_next_document(docs.select("doc_id", "text"), ["text"], rows_per_bucket=3).toPandas()
    t = docs.toPandas().sort_values("doc_id", ascending=False)
    want = dict(zip(t.doc_id, list(t.text[1:]) + [t.text.iloc[0]], strict=True))
    assert len(r) == len(t) and all(want[i] == x for i, x in zip(r.doc_id, r.next_text, strict=True))


def test_license_scan(spark):
    rows = [(1, "Released under the MIT License. Under the mit license"), (2, "licensed under the Apache License, Version 2.0."), (3, "CC BY-NC 4.0"), (4, "nothing here"), (5, None), (6, "licensed under the gnu general public license version 3"), (7, "the mit"), (7, "the mit")]
    r = license_scan.scan(spark, spark.createDataFrame(rows, "doc_id int, text string")).collect()
    got = {x["doc_id"]: x for x in r}
    assert len(r) == 8
    assert (got[1]["n_base"], got[1]["first_word"], got[1]["last_word"], got[1]["base_labels"]) == (2, 1, 5, "mit")
    assert got[2]["labels"] == "apache-2" and got[3]["base_labels"] == "cc-by-nc" and got[6]["labels"] == "gpl-3" and got[6]["base_labels"] == ""
    for i in (4, 5, 7):
        assert got[i]["n_base"] == 0 and got[i]["first_word"] is None and got[i]["labels"] == ""
    assert got[5]["n_words"] == 0 and 0 <= got[7]["score"] < 0.6


def test_encoder_equals_the_library(docs, monkeypatch):
    e = tokens.encoder(tokens.tokenizer_path())
    texts = [t for _, t, _ in ODD] + ["naïve Œuvre İstanbul I'll don't l'été", "a²b ½ x́y é", "\x1c\x85\xa0 ab​c", "ÀÉßØ×÷ a_b-c 3.14", "\x00\x01 tab\tnew\nline"]
    texts += ["''s ''tis \"'s 's't 'lls 'LL 'Re x'RE5 'd'", "a" * 500, "!" * 300 + "'s", "é́ é 'É \x7f' x'\xe9", "'", " ' ", "'s"]
    rng, letters = random.Random(1), list("aábcÉ'’.,!12 \n\tSTstrelvdm日́ß×")
    texts += ["".join(rng.choice(letters) for _ in range(rng.randint(0, 60))) for _ in range(1500)]
    texts += [r["text"] for r in docs.select("text").collect()]

    def equal(e, texts):
        ids, bounds = e.encode(pa.array(texts, pa.string()))
        assert len(bounds) == len(texts) + 1
        for i, t in enumerate(texts):
            assert ids[bounds[i] : bounds[i + 1]].tolist() == e.lib.encode(t or "", add_special_tokens=False).ids

    assert e.in_words
    equal(e, texts)
    monkeypatch.setattr(tokens, "CHUNK", 7)  # chunks end at blanks
    equal(e, texts[:300])
    other = tokens.Encoder(tokens.tokenizer_path("byte_bpe_50k.json"))  # other settings: whole texts by the library
    assert not other.in_words
    equal(other, texts[:50])
    equal(e, [])


def seek_table_of_the_public_format(raw: bytes, reader) -> None:
    """What a reader that knows the seekable format, and nothing of ours, finds."""
    frames, flags, magic = struct.unpack("<IBI", raw[-9:])
    assert (flags, magic) == (0x80, 0x8F92EAB1)
    begin = len(raw) - 9 - 12 * frames
    assert struct.unpack("<II", raw[begin - 8 : begin]) == (0x184D2A5E, 12 * frames + 9)
    at, whole = 0, b""
    for i in range(frames):
        packed, size, check = struct.unpack("<III", raw[begin + 12 * i : begin + 12 * i + 12])
        frame = raw[at : at + packed]
        plain = zstandard.ZstdDecompressor().decompress(frame) if size else b""
        assert len(plain) == size and xxhash.xxh64_intdigest(plain) & 0xFFFFFFFF == check
        at, whole = at + packed, whole + plain
    assert at == begin - 8 and whole == b"".join(reader.frame(i).tobytes() for i in range(len(reader.doc_ids)))
    stream = zstandard.ZstdDecompressor().stream_reader(io.BytesIO(raw), read_across_frames=True)
    assert stream.read() == whole


@pytest.mark.parametrize("rows", [ODD, []])
def test_token_files(spark, odd, rows, tmp_path):
    df = odd if rows else odd.where("false")
    manifest = token_store.write_shards(spark, df, "file://" + str(tmp_path / "t"), shard_bytes=50_000)
    r = sorted(token_store.read_report(spark, manifest).collect(), key=lambda x: x["start"])
    assert len(r) == len(rows)
    start, e = 0, tokens.encoder(tokens.tokenizer_path())
    for x, (i, t, _) in zip(r, sorted(rows, key=lambda y: (y[0] is not None, y[0] or 0)), strict=True):
        ids = [*e.lib.encode(t or "", add_special_tokens=False).ids, 2]
        assert (x["doc_id"], x["start"], x["n_tokens"], x["ids_crc32"]) == (i, start, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes()))
        start += len(ids)
    if rows:
        path = next(m["path"] for m in manifest if m["n_docs"]).removeprefix("file://")
        with open(path, "rb") as f:
            reader = token_store.ShardReader(f)
            assert sum(1 for _ in reader.documents()) == len(reader.doc_ids)
            one = reader.doc_ids[-1]
            assert [d for d, _ in reader.documents({one})] == [d for d in reader.doc_ids if d == one]
        raw = bytearray(open(path, "rb").read())
        seek_table_of_the_public_format(bytes(raw), token_store.ShardReader(io.BytesIO(raw)))
        raw[6] ^= 255
        open(path, "wb").write(raw)
        with open(path, "rb") as f, pytest.raises(Exception):  # noqa: B017  a broken frame is noticed
            list(token_store.ShardReader(f).documents())


def test_best_cuts_are_optimal():
    rng = np.random.default_rng(0)
    for _ in range(50):
        at = np.cumsum(rng.integers(1, 9, 14)).tolist()
        at = [0, *at]
        penalty = rng.integers(0, 6, 15).tolist()
        size = 20
        best = {0: 0}
        for j in range(1, 15):
            best[j] = min(best[i] + size - (at[j] - at[i]) + penalty[j] for i in range(j) if at[j] - at[i] <= size)
        cuts = packing.best_cuts(at, penalty, size)
        cost = sum(size - (at[b] - at[a]) + penalty[b] for a, b in zip(cuts, cuts[1:], strict=False))
        assert cuts[0] == 0 and cuts[-1] == 14 and cost == best[14]


def test_packing_covers_every_id_once(spark, odd, docs):
    for df in (odd, docs, odd.where("false")):
        p = packing.pack(spark, df, shard_bytes=100_000, chunk=5000).toPandas()
        t = df.select("doc_id", "text").toPandas()
        total = {}
        for s, g in p.sort_values("offset").groupby("sequence_id"):
            assert g.length.sum() <= 2048 and (g.length.cumsum() - g.length == g.offset).all()
            total[s] = g.length.sum()
        e = tokens.encoder(tokens.tokenizer_path())
        assert p.length.sum() == len(e.encode(pa.array(t.text, pa.string()))[0]) + len(t)
        for r in p[p.doc_id.isin([1, 7])].itertuples():
            text = t[t.doc_id == r.doc_id].text.iloc[0]
            ids = np.array([*e.lib.encode(text, add_special_tokens=False).ids, 1], "<u4")
            assert r.ids_crc32 == zlib.crc32(ids[r.start : r.start + r.length].tobytes()) and r.doc_tokens == len(ids)


def brute_ppm(train: list[bytes], text: bytes, order: int) -> float:
    ctx: list[dict] = [{} for _ in range(order + 1)]
    for x in train:
        y = b"\0" * order + x + b"\0"
        for p in range(order, len(y)):
            for k in range(order + 1):
                ctx[k].setdefault(y[p - k : p], Counter())[y[p]] += 1
    y, total = b"\0" * order + text + b"\0", 0.0
    for p in range(order, len(y)):
        out: set[int] = set()
        for k in range(order, -1, -1):
            c = ctx[k].get(y[p - k : p])
            if not c:
                continue
            left = {a: n for a, n in c.items() if a not in out}
            s = sum(left.values())
            if y[p] in left:
                total += math.log10((left[y[p]] - 0.5) / s)
                break
            if left:
                total += math.log10(0.5 * len(left) / s)
            out |= set(c)
        else:
            total -= math.log10(max(1, 256 - len(out)))
    return total


def test_ppm(spark, odd, docs):
    small = docs.where("doc_id < 30")
    r = ppm.score(spark, small, order=3, head_words=50).toPandas().set_index("doc_id")
    t = small.toPandas().set_index("doc_id").text
    held = {i: zlib.crc32(str(i).encode()) % 7 == 2 for i in t.index}
    c: Counter = Counter()
    for i, x in t.items():
        if not held[i]:
            c.update([*x.encode().lower().split(), None])
    n, v = sum(c.values()), len(c)
    train = [x.encode().lower() for i, x in t.items() if not held[i]]
    for i, x in t.items():
        w = [*x.encode().lower().split(), None]
        assert r.held_out[i] == held[i] and r.n_tokens[i] == len(w) and r.n_known[i] == sum(c[y] > 0 for y in w) and r.train_tokens[i] == n
        assert r.base_score[i] == pytest.approx(sum(math.log10((c[y] + 1) / (n + v + 1)) for y in w))
    for i in list(t.index)[:6]:
        assert r.score[i] == pytest.approx(brute_ppm(train, t[i].encode().lower(), 3))
    assert ppm.score(spark, odd, order=2).count() == len(ODD) and ppm.score(spark, odd.where("false"), order=2).count() == 0


def test_ppm_drops_no_run(spark, docs):
    small = docs.where("doc_id < 30")
    full = ppm.score(spark, small, order=3).toPandas().set_index("doc_id").score
    for most in (0, 300):  # runs beyond those in the broadcast are joined
        cut = ppm.score(spark, small, order=3, most_nodes=most).toPandas().set_index("doc_id").score
        assert len(cut) == len(full) and all(cut[i] == pytest.approx(full[i]) for i in full.index)


def test_language(spark, docs, odd):
    r = langid.identify(spark, docs).toPandas().merge(docs.toPandas()[["doc_id", "lang"]], on="doc_id")
    held = r[r.held_out]
    assert (held.lang == held.lang_pred).mean() > 0.97 and held.rejected.mean() < 0.05
    with_lang = odd.selectExpr("doc_id", "text", "'en' as lang", "n_words as score")
    got = langid.identify(spark, with_lang).toPandas()
    assert len(got) == len(ODD) and (got[got.doc_id.isin([3, 4])].lang_pred == "und").all()
    assert langid.accept(spark, docs).columns == docs.columns
    assert langid.identify(spark, with_lang.where("false")).count() == 0
    # the probabilities of all next characters after a context sum to one
    m = langid.Models(["a", "b"], list("xyz"), [(np.array([3, 7], np.uint64), np.array([2, 1])), (np.array([8], np.uint64), np.array([4]))], 2)
    for lang in range(2):
        for first in range(m.base):
            t, p = m.tables[2]
            keys = np.arange(first * m.base, (first + 1) * m.base, dtype=np.uint64)
            total = 0.0
            for k in keys:
                row = t.rows(np.array([k]))[0]
                if row >= 0:
                    total += math.exp(p[row, lang])
                    continue
                c, w = m.passed[2]
                at = c.rows(np.array([k // np.uint64(m.base)]))[0]
                back = math.exp(w[at, lang]) if at >= 0 else 1.0
                one, p1 = m.tables[1]
                r1 = one.rows(np.array([k % np.uint64(m.base)]))[0]
                c1, w1 = m.passed[1]
                total += back * (math.exp(p1[r1, lang]) if r1 >= 0 else math.exp(w1[0, lang]) / m.base)
            assert total == pytest.approx(1.0, abs=1e-4)


def test_toxicity_grammar():
    s = toxicity.Scorer({"fool": ("I", 4.0), "not": ("N", 0.0), "says": ("R", 0.0), "you": ("Y", 0.0)}, {"vile": 3.0}, dict(toxicity.FACTORS))
    assert s.clauses("the fool. not a fool; he says the fool, you fool") == [("I", 4.0), ("j", 4.0), ("i", 4.0), ("A", 4.0)]
    assert s.clauses("not one two three fool") == [("I", 4.0)] and s.clauses("vilest vile") == [("I", 3.0)]
    assert s.clauses(None) == s.clauses("") == [] and 0 < s.score("")[0] < 0.5
    assert s.score("you fool")[0] > s.score("not a fool")[0]


def test_toxicity(spark, docs, odd):
    big = common.table(spark, "/root/testdata/sf0.01", "documents")
    labels = common.table(spark, "/root/testdata/sf0.01", "labels")
    r = toxicity.classify(spark, big, labels).toPandas().merge(labels.toPandas(), on="doc_id")
    held = r[r.held_out]
    assert (held.predicted == held.toxic).mean() > 0.95 and ((r.predicted == 1) & (r.toxic == 0)).sum() <= 2
    assert (r.predicted == (r.score >= 0.5)).all()
    got = toxicity.classify(spark, odd, labels.where("false"))
    assert got.count() == len(ODD) and toxicity.classify(spark, odd.where("false"), labels).count() == 0
    assert toxicity.accept(spark, big, labels).columns == big.columns
