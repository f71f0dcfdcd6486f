"""What the sample of shingles decides: an order of filing. Which texts stay does not depend on it."""

from __future__ import annotations

import random

import numpy as np
import pytest

from unionlake.llm import near_dedup
from unionlake.llm.covering import shingle_hashes, words_of


def corpus() -> list[str]:
    pick = random.Random(5)
    word = lambda: "".join(pick.choice("abcdefgh") for _ in range(5))
    shared = [word() for _ in range(12)]
    texts = []
    for _ in range(25):
        own = [word() for _ in range(150)]
        for cut in (0, 1, 3, 6, 12):
            at = pick.randrange(len(own))
            texts.append(" ".join([*shared[: pick.randrange(12)], *own[:at], *(word() for _ in range(cut)), *own[at + cut :]]))
    return texts


@pytest.mark.parametrize("sample", ["none", "all", "reversed"])
def test_any_order_of_shingles_finds_all_pairs(spark, monkeypatch, sample):
    texts = corpus()
    own = [set(shingle_hashes(words_of(t), 5)) for t in texts]
    real = {(a, b) for b in range(len(texts)) for a in range(b) if len(own[a] & own[b]) >= 0.8 * len(own[a] | own[b])}
    keys, n = np.unique(np.concatenate([np.array(list(x), np.uint64) for x in own]), return_counts=True)
    given = {"none": (keys[:0], n[:0]), "all": (keys, n), "reversed": (keys, n.max() + 1 - n)}[sample]
    monkeypatch.setattr(near_dedup, "common_shingles", lambda *a, **k: given)
    docs = spark.createDataFrame([(i, str(i), t) for i, t in enumerate(texts)], "id bigint, text_key string, text string")
    reps = near_dedup.sketches(spark, docs, 5, 12, 0.8).selectExpr("*", "id as root").localCheckpoint()
    got = {(r["a"], r["b"]) for r in near_dedup.unconnected(spark, reps, 0.8).collect()}
    assert len(real) > 20 and real <= got
