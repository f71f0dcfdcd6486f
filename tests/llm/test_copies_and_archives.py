"""Decontamination, SimHash links, near-duplicate removal, archives and the pipeline against brute force."""

from __future__ import annotations

import hashlib
import random

import numpy as np
import pytest

import corpus_pipeline
from unionlake.llm import common, covering, decontaminate, near_dedup, warc

SF = "/root/testdata/sf0.001"


def brute_hits(text, items, width=10):
    w = decontaminate.words_of(text)
    hit, found = set(), set()
    for i, t in items:
        x = decontaminate.words_of(t)
        n = min(width, len(x))
        wins = {tuple(x[k : k + n]) for k in range(len(x) - n + 1)} if n else set()
        for k in range(len(w) - n + 1):
            if n and tuple(w[k : k + n]) in wins:
                hit |= set(range(k, k + n))
                found.add(i)
    return len(w), len(hit), found


def test_decontamination(spark):
    docs, bench = common.table(spark, SF, "documents"), common.table(spark, SF, "benchmark")
    extra = spark.createDataFrame([(900_001, None), (900_002, ""), (900_003, "x tiny item y"), (900_003, "x tiny item y"), (None, "tiny item")], "doc_id bigint, text string")
    items = spark.createDataFrame([(-5, "Tiny ITEM"), (-6, None), (-7, "...")], "item_id bigint, text string")
    every, all_items = docs.select("doc_id", "text").unionByName(extra), bench.unionByName(items)
    pairs = [(r["item_id"], r["text"]) for r in all_items.collect()]
    for limit in (1 << 20, 1500):
        got = decontaminate.scan(spark, every, all_items, limit_bytes=limit).toPandas()
        assert len(got) == every.count()
        by = got.drop_duplicates("doc_id").set_index("doc_id")
        for r in every.collect():
            if r["doc_id"] is None:
                continue
            n, hit, found = brute_hits(r["text"], pairs)
            x = by.loc[r["doc_id"]]
            assert (x.n_words, x.n_hit, x.n_items) == (n, hit, len(found))
            assert x.items_sha256 == hashlib.sha256(",".join(sorted(map(str, found))).encode()).hexdigest()
    stripped = decontaminate.clean(spark, every, all_items, "strip")
    assert stripped.count() == every.count() and decontaminate.scan(spark, stripped, all_items).where("contaminated").count() == 0
    assert decontaminate.clean(spark, every, all_items).count() == decontaminate.scan(spark, every, all_items).where("not contaminated").count()
    assert decontaminate.scan(spark, every, all_items.where("false")).where("contaminated").count() == 0
    assert decontaminate.scan(spark, every.where("false"), all_items).count() == 0


def test_masks_cover_every_pair_in_the_radius():
    rng = random.Random(0)
    for radius in (1, 2, 3):
        tables = covering.masks(radius)
        assert len(tables) == 2 ** (radius + 1) - 1
        for _ in range(2000):
            x = sum(1 << i for i in rng.sample(range(64), rng.randint(0, radius)))
            assert any(x & m == 0 for m in tables)


@pytest.mark.parametrize("bucket_rows", [200, 2])
def test_links_are_complete(spark, bucket_rows):
    rng = random.Random(1)
    fps = set()
    for _ in range(30):
        x = rng.getrandbits(64)
        for _ in range(8):
            fps.add(x)
            x ^= sum(1 << i for i in rng.sample(range(64), rng.randint(0, 3)))
    fps = sorted(fps)
    signed = lambda x: x - (1 << 64) if x >> 63 else x
    df = spark.createDataFrame([(signed(x),) for x in fps], "fp bigint")
    got = [(r["a"], r["b"]) for r in covering.links(df, 2, bucket_rows).collect()]
    want = {tuple(sorted((signed(a), signed(b)))) for i, a in enumerate(fps) for b in fps[i + 1 :] if (a ^ b).bit_count() <= 2}
    assert len(got) == len(set(got)) and set(got) == want
    edges = df.sparkSession.createDataFrame([(1, 2), (2, 3), (3, 4), (4, 5), (9, 8)], "a bigint, b bigint")
    names = spark.createDataFrame([(i, i) for i in range(12)], "node bigint, name bigint")
    assert {r["node"]: r["root"] for r in covering.components(spark, edges, names).collect()} == {1: 1, 2: 1, 3: 1, 4: 1, 5: 1, 8: 8, 9: 8}


def test_components_of_documents(spark):
    rows = [(5, "A b c d"), (3, "a B c d"), (7, None), (9, "  "), (None, "a b c d"), (4, "other words here now"), (4, "other words here now")]
    r = covering.link_components(spark, spark.createDataFrame(rows, "doc_id int, text string")).collect()
    got = {x["doc_id"]: (x["fingerprint"], x["component_id"]) for x in r}
    assert len(r) == 7 and got[5][1] == got[3][1] == got[None][1] == 3 and got[7] == got[9] == ("0" * 16, 7) and got[4][1] == 4
    x = covering.majority(covering.shingle_hashes([b"a", b"b", b"c", b"d"], 3))
    import xxhash

    h = [xxhash.xxh64_intdigest(s, 42) for s in (b"a b c", b"b c d")]
    assert x == h[0] & h[1] and got[5][0] == f"{x:016x}"


def test_near_copies_go_and_others_stay(spark):
    rng = random.Random(2)
    vocabulary = ["".join(rng.choice("abcdefghij") for _ in range(5)) for _ in range(3000)]
    passage = [rng.choice(vocabulary) for _ in range(60)]
    texts, want = {}, set()
    for g in range(40):
        base = [rng.choice(vocabulary) for _ in range(rng.randint(120, 400))] + passage
        for c in range(60 if g == 0 else 3):
            w = list(base)
            for i in rng.sample(range(len(w)), len(w) // 90 if c else 0):
                w[i] = rng.choice(vocabulary)
            texts[g * 1000 + c] = " ".join(w)
    sets = {i: set(covering.shingle_hashes(t.encode().split(), 5)) for i, t in texts.items()}
    root = {i: i for i in texts}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    ids = sorted(texts)
    for a in ids:
        for b in ids:
            if a < b and a // 1000 == b // 1000 and len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b]):
                x, y = find(a), find(b)
                root[max(x, y)] = min(x, y)
    want = {find(i) for i in ids}
    rows = [(i, t, "k") for i, t in texts.items()] + [(None, "lonely words without an id at all", "k"), (90_000, None, "k"), (90_001, "", "k")]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string, key string")
    kept = near_dedup.keep_first(spark, docs)
    assert kept.columns == docs.columns
    got = {r["doc_id"] for r in kept.collect()}
    assert got - want == {None, 90_000} and want - got == set()
    assert near_dedup.keep_first(spark, docs.where("false")).count() == 0


def brute_firsts(texts):
    """The smallest id of each component of the texts {id: text} under the pipeline's similarity."""
    sets = {i: set(covering.shingle_hashes(t.encode().split(), 5)) for i, t in texts.items()}
    root = {i: i for i in texts}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    ids = sorted(texts)
    for n, a in enumerate(ids):
        for b in ids[n + 1 :]:
            if len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b]):
                x, y = find(a), find(b)
                root[max(x, y)] = min(x, y)
    return {find(i) for i in ids}


def kept_of(spark, texts):
    docs = spark.createDataFrame(list(texts.items()), "doc_id bigint, text string")
    return {r["doc_id"] for r in near_dedup.keep_first(spark, docs).collect()}


def test_edits_of_a_source_with_the_largest_id(spark):
    rng = random.Random(3)
    source = [f"s{i}" for i in range(300)]
    texts = {300: " ".join(source)}
    for c in range(300):
        w = list(source)
        for i in rng.sample(range(0, 300, 8), 6):  # below the similarity between two edits, above it to the source
            w[i] = f"e{c}x{i}"
        texts[c] = " ".join(w)
    sets = [set(covering.shingle_hashes(t.encode().split(), 5)) for t in texts.values()]
    far = sum(len(a & b) < 0.8 * len(a | b) for i, a in enumerate(sets[1:]) for b in sets[i + 2 :])
    assert far > 0.9 * 300 * 299 / 2
    assert brute_firsts(texts) == {0} == kept_of(spark, texts)


def test_short_near_copies(spark):
    rng = random.Random(4)
    texts = {}
    for g in range(60):
        w = [f"w{rng.randrange(10**6)}" for _ in range(8 + g % 20)]
        texts[2 * g], texts[2 * g + 1] = " ".join(w), " ".join([*w, "more"])
    firsts = brute_firsts(texts)
    assert len(firsts) < 70
    assert kept_of(spark, texts) == firsts


def test_a_repeated_passage_and_edited_blocks(spark):
    rng = random.Random(5)
    texts = {}
    for g in range(8):
        w = [f"w{rng.randrange(10**6)}" for _ in range(800)]
        texts[10 * g], texts[10 * g + 1] = " ".join(w), " ".join(w + w[100:140] * 60)  # the fingerprint follows the passage
        for c in range(2, 5):  # edits all over the text, so that few blocks are left whole
            e = list(w)
            for i in range(20 + c, 780, 45):
                e[i] = f"e{c}x{i}"
            texts[10 * g + c] = " ".join(e)
    firsts = brute_firsts(texts)
    assert firsts == {10 * g for g in range(8)}
    assert kept_of(spark, texts) == firsts


def test_chunks_and_records():
    for n in (0, 1, 8192, 20_000):
        p = bytes(range(256)) * (n // 256) + b"x" * (n % 256)
        assert warc.unchunked(warc.chunked(p)) == p
    with pytest.raises(ValueError):
        warc.unchunked(b"5\r\nabcdeXX0\r\n\r\n")


def test_archives(spark, tmp_path):
    big = "<p>" + "z" * 90_000 + "é</p>"
    rows = [(1, "u", big), (2, "u", big), (9, None, big), (3, "u", "small"), (4, "u", "small"), (5, "u", None), (None, "u", big), (6, "u", "y" * 1000), (6, "u", "y" * 1000)]
    pages = spark.createDataFrame([(*r, 1) for r in rows], "page_id bigint, url string, html string, payload_digest int")
    r = warc.round_trip(spark, pages).collect()
    assert len(r) == len(rows)
    got = {x["page_id"]: x for x in r}
    for i, _, h in rows:
        raw = (h or "").encode()
        assert (got[i]["payload_bytes"], got[i]["payload_digest"]) == (len(raw), hashlib.sha1(raw).hexdigest())
    assert [(got[i]["record_type"], got[i]["refers_to"]) for i in (1, 2, 9, 3, 4, 5, None)] == [("revisit", 9), ("revisit", 9), *[("response", None)] * 5]
    paths = warc.write_archives(spark, pages, "file://" + str(tmp_path / "w"), segment_bytes=1000)
    segments = warc.read_segments(spark, paths).persist()
    assert segments.where("kind = 'continuation'").count() > 100
    assert warc.payloads(warc.reassemble(segments)).count() == len(rows)
    with pytest.raises(Exception):  # noqa: B017  a lost segment is an error, not a short payload
        warc.payloads(warc.reassemble(segments.where("number != 2"))).collect()
    assert warc.round_trip(spark, pages.where("false")).count() == 0


def test_pipeline(spark):
    docs = common.table(spark, SF, "documents")
    frames, cur = [docs], docs
    for _, stage in corpus_pipeline.STAGES[:-1]:
        cur = common.checkpointed(spark, stage(spark, cur, SF), "t")
        assert cur.columns == docs.columns
        frames.append(cur)
    ids = [{r["doc_id"] for r in f.select("doc_id").collect()} for f in frames]
    assert all(b <= a for a, b in zip(ids, ids[1:], strict=False)) and len(ids[-1]) > 0.7 * len(ids[0])
    pairs = [(r["item_id"], r["text"]) for r in common.table(spark, SF, "benchmark").collect()]
    assert not any(brute_hits(r["text"], pairs)[1] for r in cur.collect())
    packed = corpus_pipeline.STAGES[-1][1](spark, cur, SF)
    assert {r["doc_id"] for r in packed.select("doc_id").distinct().collect()} == ids[-1]
    assert np.unique([len(x) for x in ids])[0] > 0
