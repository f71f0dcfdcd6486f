"""Pairs that only share a passage go before their texts move; near copies do not."""

from __future__ import annotations

import random

import numpy as np

from unionlake.llm import near_dedup
from unionlake.llm.covering import shingle_hashes, words_of


def test_parities_bound_the_difference():
    pick = random.Random(7)
    for _ in range(300):
        common = [pick.getrandbits(64) for _ in range(pick.randint(0, 300))]
        one, two = ({*common, *(pick.getrandbits(64) for _ in range(pick.randint(0, 90)))} for _ in range(2))
        p, q = (near_dedup.parities(np.unique(np.array(list(x), np.uint64))) for x in (one, two))
        assert near_dedup.fewest_apart(p, q) == near_dedup.fewest_apart(q, p) <= len(one ^ two)


def test_passages_are_no_pairs_and_near_copies_are(spark):
    pick = random.Random(8)
    word = lambda: "".join(pick.choice("abcdefgh") for _ in range(6))
    passage = [word() for _ in range(25)]
    texts = [[*passage, *(word() for _ in range(150 + 2 * i))] for i in range(30)]
    texts += [[*t[:-4], word()] for t in texts[:5]]
    docs = spark.createDataFrame([(i, str(i), " ".join(t)) for i, t in enumerate(texts)], "id bigint, text_key string, text string")
    reps = near_dedup.sketches(spark, docs, 5, 12, 0.8).localCheckpoint()
    every = spark.createDataFrame([(a, b) for b in range(35) for a in range(b)], "a bigint, b bigint")
    left = {(r["a"], r["b"]) for r in near_dedup.close(every, reps, 0.8).collect()}
    own = [set(shingle_hashes(words_of(" ".join(t)), 5)) for t in texts]
    real = {(a, b) for b in range(35) for a in range(b) if len(own[a] & own[b]) >= 0.8 * len(own[a] | own[b])}
    assert real == {(i, 30 + i) for i in range(5)} and real <= left and len(left) < 10
