"""The pipeline's near-duplicate stage against brute-force Jaccard similarity."""

from itertools import combinations

import numpy as np
import pytest
from conftest import SF
from test_operators import lower, spaced

import corpus_pipeline as cp
from dpsynth.llm import nearcopies


def brute_shingles(text):
    w = spaced(lower(text))
    return {" ".join(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()


def brute_kept(texts):
    """Ids of texts (a dict) that are the smallest of their component of Jaccard similarities of 0.8 or more."""
    sets, least = {i: brute_shingles(t) for i, t in texts.items()}, {i: i for i in texts}

    def find(x):
        while least[x] != x:
            x = least[x]
        return x

    for i, j in combinations(sorted(texts), 2):
        x, y = sets[i], sets[j]
        if x == y or 5 * len(x & y) >= 4 * len(x | y):
            a, b = find(i), find(j)
            least[max(a, b)] = min(a, b)
    return {i for i in texts if find(i) == i}


def test_stage_equals_brute_force_on_documents(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    want = brute_kept({r["doc_id"]: r["text"] for r in docs.collect()})
    assert {r["doc_id"] for r in cp.dedup_documents(spark, docs, SF).collect()} == want


@pytest.mark.parametrize("block", [1000, 7])
def test_stage_equals_brute_force_around_the_threshold(spark, monkeypatch, block):
    monkeypatch.setattr(nearcopies, "BLOCK_DOCS", block)
    rng = np.random.default_rng(4)
    texts = {}
    for base in range(8):
        words = [f"w{x}" for x in rng.integers(0, 5000, rng.integers(6, 200))]
        for _ in range(12):
            copy = list(words)
            for _ in range(rng.integers(0, 1 + len(words) // 25)):
                copy[rng.integers(len(copy))] = f"x{rng.integers(9999)}"
            texts[len(texts)] = " ".join(copy)
    texts |= {len(texts): "", len(texts) + 1: " \n", len(texts) + 2: "one two"}
    frame = spark.createDataFrame([(i, t, 1) for i, t in texts.items()], "doc_id long, text string, n_chars long")
    assert {r["doc_id"] for r in nearcopies.keep_one(frame).collect()} == brute_kept(texts)


def test_intersections_of_common_and_rare_shingles():
    rng = np.random.default_rng(5)
    sets = [np.unique(rng.integers(0, 400, rng.integers(1, 300))).astype(np.uint64) for _ in range(90)]
    found = nearcopies.intersections(sets)
    assert all(found[i, j] == len(np.intersect1d(sets[i], sets[j])) for i, j in combinations(range(90), 2))
