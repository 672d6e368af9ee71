"""Exact dedup, SimHash near-dedup and line dedup against brute force, and their edge cases."""

from __future__ import annotations

import hashlib
import random
import re
from collections import Counter

import pytest
from pyspark.sql import functions as F

from idfold.llm import exact_dedup, line_dedup, simhash_pivots
from idfold.llm.components import components

SCHEMA = "doc_id long, text string, lang string, source string, digest string, fp long"
TEXTS = ["a b", "ab", "a\nb ", None, "", " \t", "x", "x", "é ü", "w " * 3000, "A b"]


def frame(spark, texts, ids=None):
    ids = ids or list(range(len(texts)))
    return spark.createDataFrame([(i, t, "en", "s", "clash", 7) for i, t in zip(ids, texts, strict=True)], SCHEMA)


@pytest.fixture(scope="module")
def stored(spark, tmp_path_factory):
    """Documents behave as a file scan, as they do in production."""

    def make(df):
        path = str(tmp_path_factory.mktemp("docs") / "d")
        df.write.parquet(path)
        return spark.read.schema(df.schema).parquet(path)

    return make


def test_exact_against_brute_force(spark, stored):
    rng = random.Random(1)
    texts = [rng.choice(TEXTS) for _ in range(300)]
    ids = [rng.choice([None, *range(200)]) for _ in texts]
    got = exact_dedup.exact_dedup(stored(frame(spark, texts, ids)), counters=4).collect()
    assert len(got) == 300
    norm = [re.sub(r"[\x20\x09-\x0D]", "", t or "") for t in texts]
    sizes = Counter(norm)
    for r in got:
        n = next(x for x in sizes if hashlib.sha256(x.encode()).hexdigest() == r["text_sha256"])
        group = sorted((-len(t or ""), i is None, i or 0) for t, i, m in zip(texts, ids, norm, strict=True) if m == n)
        assert r["group_size"] == sizes[n]
        assert r["keep_id"] == (None if group[0][1] else group[0][2])
    assert sum(r["kept"] for r in got) == len(sizes)


def test_exact_winners_keep_columns(spark, stored):
    docs = stored(frame(spark, TEXTS))
    kept = exact_dedup.keep_winners(docs)
    assert kept.columns == docs.columns
    assert sorted(r["doc_id"] for r in kept.collect()) == [2, 5, 6, 8, 9, 10]


def test_misra_gries_keeps_every_frequent_key():
    rng = random.Random(2)
    items = ["hot"] * 400 + [str(rng.randrange(500)) for _ in range(800)]
    rng.shuffle(items)
    summary = Counter()
    for at in range(0, len(items), 50):
        summary = exact_dedup.misra_gries(summary, Counter(items[at : at + 50]), 3)
        assert len(summary) <= 3
    assert "hot" in summary


def test_empty_tables(spark, stored):
    docs = stored(frame(spark, TEXTS).where("false"))
    assert exact_dedup.exact_dedup(docs).count() == 0
    assert simhash_pivots.near_dedup(docs).count() == 0
    assert line_dedup.dedup_lines(docs).count() == 0


def brute_fp(text):
    import xxhash

    words = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
    if not words:
        return 0
    grams = [" ".join(words[i : i + 3]) for i in range(len(words) - 2)] or [" ".join(words)]
    hashes = [xxhash.xxh64_intdigest(g.encode(), seed=42) for g in grams]
    return sum(1 << k for k in range(64) if 2 * sum(h >> k & 1 for h in hashes) > len(hashes))


def brute_components(fps, ids):
    label = list(range(len(fps)))
    changed = True
    while changed:
        changed = False
        for i in range(len(fps)):
            for j in range(len(fps)):
                if label[j] < label[i] and bin(fps[i] ^ fps[j]).count("1") <= 2:
                    label[i], changed = label[j], True
    return [min((ids[j] for j in range(len(ids)) if label[j] == label[i] and ids[j] is not None), default=None) for i in range(len(ids))]


def test_fingerprints_and_components(spark, stored):
    rng = random.Random(3)
    base = [rng.choice("alpha beta gamma delta epsilon zeta eta theta".split()) for _ in range(200)]
    texts = list(TEXTS)
    for _ in range(40):
        words = list(base)
        for _ in range(rng.randrange(3)):
            words[rng.randrange(len(words))] = rng.choice(["UPPER", "x", "beta"])
        texts.append(" ".join(words))
    got = {r["doc_id"]: r for r in simhash_pivots.near_dedup(stored(frame(spark, texts))).collect()}
    fps = [brute_fp(t) for t in texts]
    assert [got[i]["fingerprint"] for i in range(len(texts))] == [f"{f:016x}" for f in fps]
    assert [got[i]["component_id"] for i in range(len(texts))] == brute_components(fps, list(range(len(texts))))


@pytest.mark.parametrize("bucket", [1, 3, 32])
def test_dense_neighbourhoods_lose_no_link(spark, bucket, monkeypatch):
    """Fingerprints around a few centres, whichever way crowded buckets are linked."""
    monkeypatch.setattr(simhash_pivots, "PAIR_BUCKET", bucket)
    rng = random.Random(4)
    fps = set()
    for _ in range(4):
        centre = rng.getrandbits(64)
        for _ in range(40):
            x = centre
            for _ in range(rng.randrange(5)):
                x ^= 1 << rng.randrange(64)
            fps.add(x)
    fps = sorted(fps)
    df = spark.createDataFrame([(simhash_pivots._signed(f), i) for i, f in enumerate(fps)], "fp long, least long")
    labels = {r["node"]: r["label"] for r in components(simhash_pivots.near_links(df)).collect()}
    want = brute_components(fps, list(range(len(fps))))
    groups = {}
    for f, w in zip(fps, want, strict=True):
        s = simhash_pivots._signed(f)
        groups.setdefault(w, set()).add(labels.get(s, s))
    assert all(len(g) == 1 for g in groups.values()) and len({next(iter(g)) for g in groups.values()}) == len(groups)


def test_long_chains_are_one_component(spark):
    links = spark.createDataFrame([(i, i + 1) for i in range(60)] + [(100, 100), (200, 201)], "a long, b long")
    got = {r["node"]: r["label"] for r in components(links).collect()}
    assert {got[i] for i in range(61)} == {0} and got[201] == 200 and 100 not in got


def test_one_row_of_each_component_stays(spark, stored):
    docs = stored(frame(spark, ["a b c d", "a b c d", "A b c d", None, "", "other text here now"], [5, 3, 3, None, None, 9]))
    kept = simhash_pivots.keep_first(docs)
    assert kept.columns == docs.columns
    assert sorted(str(r["doc_id"]) for r in kept.collect()) == ["3", "9", "None"]


def brute_lines(texts):
    """Winnowed grams of two lines, windows of two; long lines by themselves; matches extended by three lines."""
    import xxhash

    def signed(x):
        return x - (1 << 64) if x >= 1 << 63 else x

    def h64(s, seed=42):
        return signed(xxhash.xxh64_intdigest(s.encode(), seed=seed & (2**64 - 1)))

    def hlong(v, seed):
        return signed(xxhash.xxh64_intdigest((v & (2**64 - 1)).to_bytes(8, "little"), seed=seed & (2**64 - 1)))

    seqs, anchors = [], []
    for d, t in enumerate(texts):
        seq = [(i, h64(x.strip(" \t\n\x0b\x0c\r")), len(x.strip(" \t\n\x0b\x0c\r")) >= 200) for i, x in enumerate((t or "").split("\n")) if x.strip(" \t\n\x0b\x0c\r")]
        seqs.append(seq)
        grams = [(hlong(seq[i + 1][1], hlong(seq[i][1], 42)), -i) for i in range(len(seq) - 1)]
        picked = {min(grams[i : i + 2]) for i in range(max(len(grams) - 1, min(len(grams), 1)))}
        anchors += [(k, d, -m, 2) for k, m in picked]
        anchors += [(h64("long", hlong(h, 42)), d, i, 1) for i, (_, h, long) in enumerate(seq) if long]
    gone = {d: set() for d in range(len(texts))}
    first = {}
    for k, d, at, n in sorted(anchors, key=lambda a: (a[1], a[2])):
        first.setdefault(k, (d, at))
        fd, fat = first[k]
        if (fd, fat) == (d, at):
            continue
        mine, theirs = seqs[d], seqs[fd]
        gone[d] |= {mine[i][0] for i in range(at, at + n)}
        for step, edge, f_edge in ((-1, at - 1, fat - 1), (1, at + n, fat + n)):
            for _ in range(3):
                if not (0 <= edge < len(mine) and 0 <= f_edge < len(theirs)) or mine[edge][1] != theirs[f_edge][1]:
                    break
                gone[d].add(mine[edge][0])
                edge, f_edge = edge + step, f_edge + step
    return gone


def test_lines_against_brute_force(spark, stored):
    rng = random.Random(5)
    pool = [f"line number {i}" for i in range(14)] + ["long " * 60, "", "  "]
    texts = [rng.choice([None, ""]) if rng.random() < 0.1 else "\n".join(rng.choice(pool) for _ in range(rng.randrange(1, 12))) for _ in range(60)]
    texts[7] = texts[3]
    got = {r["doc_id"]: r for r in line_dedup.dedup_lines(stored(frame(spark, texts))).collect()}
    want = brute_lines(texts)
    for d, t in enumerate(texts):
        assert set(got[d]["removed"]) == want[d], d
        assert got[d]["text"] == (None if t is None else "\n".join(x for i, x in enumerate(t.split("\n")) if i not in want[d]))


def test_repeated_runs_go_and_first_lines_stay(spark, stored):
    run = ["first passage line", "second passage line", "third passage line"]
    texts = ["\n".join(["own a", *run, "own b"]), "\n".join(["own c", *run, "own d"]), "\n".join(run)]
    got = {r["doc_id"]: r["text"] for r in line_dedup.dedup_lines(stored(frame(spark, texts))).collect()}
    assert got == {0: texts[0], 1: "own c\nown d", 2: ""}
    lines = set(x for t in texts for x in t.split("\n"))
    assert lines == set(x for t in got.values() for x in t.split("\n") if x)


def test_queries_cover_all_rows(spark):
    from tests.conftest import SF

    n = spark.read.parquet(f"{SF}/documents.parquet").count()
    for q in (exact_dedup.op7_exact_dedup, simhash_pivots.op1_simhash_pivots, line_dedup.op5_winnowed_lines):
        df = q(spark, SF)
        assert df.count() == n and df.select(F.count_distinct("doc_id")).first()[0] == n
