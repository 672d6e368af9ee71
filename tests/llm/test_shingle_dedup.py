"""The pipeline's near-dedup stage against brute force on planted near copies."""

from __future__ import annotations

import random

import numpy as np

import corpus_pipeline
from idfold.llm import shingle_dedup

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def shingles(text):
    words = (text or "").lower().split()
    return {" ".join(words[k : k + 5]) for k in range(max(1, len(words) - 4))}


def test_stage_finds_planted_near_copies(spark, tmp_path):
    """Copies with up to five per cent of their words changed, one large group, and a common opening."""
    rng = random.Random(11)
    word = lambda: f"w{rng.randrange(3000)}"
    opening = [word() for _ in range(40)]
    texts = []
    for _ in range(60):
        base = opening + [word() for _ in range(rng.randrange(60, 400))]
        for _ in range(3):
            copy = list(base)
            for _ in range(rng.randrange(1 + len(base) // 20)):
                copy[rng.randrange(len(copy))] = word()
            texts.append(" ".join(copy))
    hot = [word() for _ in range(150)]
    for k in range(120):
        texts.append(" ".join(hot[:k] + [word()] + hot[k + 1 :]))
    texts += ["one two", "One  two", "one two three", None, ""]
    rng.shuffle(texts)
    label, sets = list(range(len(texts))), [shingles(t) for t in texts]
    for i in range(len(texts)):
        for j in range(i):
            if label[i] != label[j] and len(sets[i] & sets[j]) >= 0.8 * len(sets[i] | sets[j]):
                old, new = max(label[i], label[j]), min(label[i], label[j])
                label = [new if v == old else v for v in label]
    path = str(tmp_path / "d")
    spark.createDataFrame([(i, t, "en", "s", 0) for i, t in enumerate(texts)], SCHEMA).write.parquet(path)
    kept = corpus_pipeline.near_copies(spark, spark.read.parquet(path), "")
    assert {r["doc_id"] for r in kept.collect()} == set(label)


def test_parities_differ_in_no_more_cells_than_the_sets_in_shingles():
    rng = np.random.default_rng(3)
    for _ in range(200):
        common, a, b = (rng.integers(0, 1 << 63, size=rng.integers(0, 900)).astype(np.uint64) * np.uint64(2) for _ in range(3))
        x, y = np.union1d(common, a), np.union1d(common, b)
        cells = np.bitwise_count((shingle_dedup.parities(x) ^ shingle_dedup.parities(y)).view(np.uint64)).sum()
        assert cells <= len(np.setxor1d(x, y))


def test_chained_copies_of_one_text_have_the_links_of_brute_force(spark, tmp_path):
    """Copies with none to six changed words: many pairs lie just below the similarity."""
    rng = random.Random(5)
    base = [f"w{rng.randrange(5000)}" for _ in range(150)]
    texts = []
    for _ in range(250):
        copy = list(base)
        for at in rng.sample(range(150), rng.randrange(7)):
            copy[at] = f"v{rng.randrange(5000)}"
        texts.append(" ".join(copy))
    label, sets = list(range(len(texts))), [shingles(t) for t in texts]
    for i in range(len(texts)):
        for j in range(i):
            if label[i] != label[j] and len(sets[i] & sets[j]) >= 0.8 * len(sets[i] | sets[j]):
                old, new = max(label[i], label[j]), min(label[i], label[j])
                label = [new if v == old else v for v in label]
    assert 10 < len(set(label)) < 200
    path = str(tmp_path / "d")
    spark.createDataFrame([(i, t, "en", "s", 0) for i, t in enumerate(texts)], SCHEMA).write.parquet(path)
    kept = shingle_dedup.keep_first(spark.read.parquet(path))
    assert {r["doc_id"] for r in kept.collect()} == set(label)


def test_nearest_copies_come_by_simhash_distance_tables(spark, tmp_path):
    rng = random.Random(8)
    base = [f"w{rng.randrange(9000)}" for _ in range(3000)]
    texts = [" ".join(base), " ".join([*base, "more"]), " ".join(f"v{rng.randrange(9000)}" for _ in range(3000)), ""]
    path = str(tmp_path / "d")
    spark.createDataFrame([(i, t, "en", "s", 0) for i, t in enumerate(texts)], SCHEMA).coalesce(1).write.parquet(path)
    found = shingle_dedup.sketches(spark.read.parquet(path), shingle=5, id_col="doc_id", text_col="text")
    pairs = shingle_dedup.simhash_pairs(found.withColumnRenamed("__row_uid", "node")).collect()
    assert {frozenset((r["a"], r["b"])) for r in pairs} == {frozenset((0, 1))}
