"""Quality rules, classifier, sharding, mixing and URL rules: brute force and edge cases."""

from __future__ import annotations

import math
import random
import re
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from idfold.llm import hash_tree, mixing, quality_rules, text_stats, url_rules, weak_quality
from tests.conftest import SF

SCHEMA = "doc_id long, text string, lang string, source string, stratum string, shard int, topic string"
TEXTS = [None, "", "  \n\t", "a", "a a a a a a a a a a a a", "one | two ### % <x>", "same line\nsame line\n\nsame line", "Ünï cödé wörds", "w " * 40000, "x\x0by\x0cz"]


def frame(spark, texts, n_ids=None):
    return spark.createDataFrame([(i, t, ["en", None][i % 2], "s", "clash", 3, "t") for i, t in enumerate(texts)], SCHEMA)


def brute_stats(text):
    text = text or ""
    words = re.findall(r"[^\x20\x09-\x0D]+", text)
    lines = [x for x in text.split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
    windows = [tuple(words[i : i + 5]) for i in range(len(words) - 4)]
    seen = {}
    for w in windows:
        seen[w] = seen.get(w, 0) + 1
    covered = {i + k for i, w in enumerate(windows) if seen[w] > 1 for k in range(5)}
    return (len(words), sum(map(len, words)), len(re.findall(r"[#*$%&|<>]", text)), len(lines) - len(set(lines)), len(covered))


def test_base_counts(spark):
    rng = random.Random(1)
    texts = TEXTS + [" ".join(rng.choice("abc") for _ in range(rng.randrange(40))) for _ in range(60)]
    got = frame(spark, texts).select("doc_id", text_stats.base_struct(F.col("text")).alias("s")).select("doc_id", "s.*").collect()
    for r in got:
        assert (r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"]) == brute_stats(texts[r["doc_id"]]), r["doc_id"]


def test_binomial_tail(spark):
    cases = [(0, 10, 0.1), (3, 10, 0.1), (0, 2000, 0.005), (4, 2000, 0.005), (10, 2000, 0.005), (0, 0, 0.1)]
    for k, n, p in cases:
        want = 1.0 if n == 0 or k >= n * p else sum(math.comb(n, i) * p**i * (1 - p) ** (n - i) for i in range(k + 1))
        got = spark.range(1).select(quality_rules.binomial_tail(F.lit(k).cast("long"), F.lit(n).cast("long"), p).alias("t")).first()["t"]
        assert abs(got - want) < 1e-9


def test_chosen_cutoffs_are_certified(spark):
    """Good texts score at most 30, bad ones 500: the cutoff must part them without losing good ones."""
    rows = [(i, "en", False, 10 * (i % 4) if i % 5 else 500) for i in range(20000)]
    m = spark.createDataFrame(rows, "doc_id long, stratum string, base_failed boolean, symbols long")
    m = m.withColumns({r: F.lit(0).cast("long") for r in quality_rules.RULES if r != "symbols"})
    labels = spark.createDataFrame([(i, 0 if i % 5 == 0 else 1) for i in range(20000)], "doc_id long, quality int")
    got = {r["rule"]: r["cutoff"] for r in quality_rules.certify(m, labels).collect()}
    assert got == {"symbols": 450}
    few = labels.where("doc_id < 100")
    assert quality_rules.certify(m, few).count() == 0


def test_quality_rules_edges(spark):
    docs = frame(spark, TEXTS)
    got = {r["doc_id"]: r for r in quality_rules.judge(docs, spark.createDataFrame([], "doc_id long, quality int")).collect()}
    assert len(got) == len(TEXTS) and not any(got[i]["kept"] for i in range(4)) and got[4]["base_failed"]
    assert quality_rules.judge(docs.where("false"), spark.createDataFrame([], "doc_id long, quality int")).count() == 0


def test_em_recovers_labeller_accuracies():
    rng = np.random.default_rng(7)
    truth = rng.random(30000) < 0.8
    right = np.array([[0.9, 0.95], [0.8, 0.99], [0.7, 0.9], [0.85, 0.97]])
    votes = np.stack([np.where(rng.random(30000) < np.where(truth, r[1], r[0]), truth, ~truth) for r in right], 1).astype(int)
    patterns, counts = np.unique(votes, axis=0, return_counts=True)
    post, accuracy, share = weak_quality.fit_labellers([(tuple(map(int, p)), int(c)) for p, c in zip(patterns, counts, strict=True)])
    assert np.abs(accuracy - right).max() < 0.05 and abs(share - 0.8) < 0.03
    assert post[(1, 1, 1, 1)] > 0.99 and post[(0, 0, 0, 0)] < 0.01


def test_classifier_on_held_out_labels(spark):
    sf = SF.replace("0.001", "0.1")
    got = weak_quality.op2_weak_label_classifier(spark, sf).join(spark.read.parquet(f"{sf}/labels.parquet"), "doc_id")
    r = got.agg(F.avg(F.when(F.col("quality") == 1, F.col("kept").cast("int"))).alias("good"), F.avg(F.when(F.col("quality") == 0, F.col("kept").cast("int"))).alias("bad")).first()
    assert r["good"] > 0.995 and r["bad"] < 0.1


def test_classifier_edges(spark):
    got = weak_quality.classify(frame(spark, TEXTS), train_texts=4)
    assert got.count() == len(TEXTS) and got.where("score is null or isnan(score)").count() == 0
    assert weak_quality.classify(frame(spark, TEXTS).where("false")).count() == 0
    assert weak_quality.keep_good(frame(spark, TEXTS)).columns == frame(spark, TEXTS).columns


def brute_shard(key, leaves):
    import hashlib

    def draw(name):
        return (int(hashlib.md5(f"{key}:{name}".encode()).hexdigest()[:12], 16) + 0.5) / 2**48

    def pick(path, weights):
        return min(sorted(weights), key=lambda n: -math.log(draw("/".join([*path, n]))) / weights[n]) if len(weights) > 1 else next(iter(weights))

    def total(level, pool):
        out = {}
        for leaf in pool:
            name = str(getattr(leaf, level))
            out[name] = out.get(name, 0.0) + leaf.weight
        return out

    pool, path = [x for x in leaves if x.weight > 0], []
    for level in ("region", "rack", "shard"):
        chosen = pick(path, total(level, pool))
        path.append(chosen)
        pool = [x for x in pool if str(getattr(x, level)) == chosen]
    return pool[0].shard


def test_equal_names_draw_apart(spark):
    """Racks named like their regions: all four leaves get their share."""
    tree = tuple(hash_tree.Leaf(r, k, i) for i, (r, k) in enumerate((r, k) for r in "ab" for k in "ab"))
    got = {r["s"]: r["count"] for r in spark.range(8000).select(hash_tree.descend(F.col("id"), tree).alias("s")).groupBy("s").count().collect()}
    assert set(got) == {0, 1, 2, 3} and all(1800 < n < 2200 for n in got.values())


def test_long_binomial_tails_are_exact(spark):
    """Tails of thousands to millions of terms against sums of log-gamma terms."""
    for k, n, p in ((4_900, 1_000_000, 0.005), (1_001, 300_000, 0.004), (250_000, 50_500_000, 0.005), (300_000, 100_000_000, 0.005)):
        log = lambda i: math.lgamma(n + 1) - math.lgamma(i + 1) - math.lgamma(n - i + 1) + i * math.log(p) + (n - i) * math.log1p(-p)
        want = sum(math.exp(log(i)) for i in range(max(0, k - 20_000), k + 1))
        got = spark.range(1).select(quality_rules.binomial_tail(F.lit(k).cast("long"), F.lit(n).cast("long"), p).alias("t")).first()["t"]
        assert got == pytest.approx(want, rel=1e-4, abs=1e-300)


def test_shards_against_brute_force(spark):
    docs = frame(spark, [f"text {i}" for i in range(400)] + TEXTS).unionByName(frame(spark, TEXTS))
    got = hash_tree.shard_rows(docs, slot_buckets=4).collect()
    assert len(got) == 400 + 2 * len(TEXTS)
    eight, nine = hash_tree.default_tree(8), hash_tree.default_tree(9)
    for r in got:
        assert r["shard"] == brute_shard(r["doc_id"], eight) and r["grown_shard"] == brute_shard(r["doc_id"], nine)
        assert r["grown_shard"] in (r["shard"], 8)
    for s in range(8):
        slots = sorted(r["slot"] for r in got if r["shard"] == s)
        assert slots == list(range(len(slots)))
    sample = next(r for r in got if r["doc_id"] == 7 and r["size"] == 7)
    assert sample["text_crc32"] == zlib.crc32(b"text 7")
    null = next(r for r in got if r["size"] == 1)
    assert null["text_crc32"] == 0


def test_weight_changes_stay_in_their_subtree(spark):
    before = hash_tree.default_tree(8)
    after = tuple(hash_tree.Leaf(x.region, x.rack, x.shard, 3.0 if x.shard == 5 else 1.0) for x in before)
    df = spark.range(4000).select(hash_tree.descend(F.col("id"), before).alias("a"), hash_tree.descend(F.col("id"), after).alias("b"))
    moved = df.where("a != b").collect()
    assert moved and all(r["b"] in (4, 5, 6, 7) for r in moved if r["a"] < 4) and not any(r["b"] < 4 for r in moved)
    share = {r["a"]: r["n"] for r in df.groupBy("a").agg(F.count("*").alias("n")).collect()}
    assert all(400 < share[s] < 600 for s in range(8))
    with pytest.raises(ValueError):
        hash_tree.descend(F.col("id"), (hash_tree.Leaf("r", "k", 0, 0.0),))


def test_raking_meets_targets(spark):
    rng = random.Random(3)
    rows = [(f"s{i}", lang, topic, rng.randrange(50, 500)) for i in range(5) for lang in ("en", "de") for topic in ("prose", "list")]
    cells = spark.createDataFrame(rows, "source string, lang string, topic string, tokens long")
    want = {"source": [(f"s{i}", (i + 1) / 15) for i in range(5)], "lang": [("en", 0.3), ("de", 0.7)], "topic": [("prose", 0.5), ("list", 0.5)]}
    targets = {m: spark.createDataFrame(v, f"{m} string, share double") for m, v in want.items()}
    raked = mixing.rake(cells, targets, rounds=12)
    total = sum(r[3] for r in rows)
    for m, v in want.items():
        got = {r[m]: r["w"] for r in raked.groupBy(m).agg(F.sum("weight").alias("w")).collect()}
        assert all(abs(got[k] / total - s) < 1e-3 for k, s in v)


def test_mixing_edges(spark):
    docs = frame(spark, TEXTS)
    got = mixing.mix(docs)
    assert got.count() == len(TEXTS) and got.where("probability < 0 or probability > 1").count() == 0
    assert mixing.mix(docs.where("false")).count() == 0
    kept = sorted(r["doc_id"] for r in got.where("kept").collect())
    sampled = mixing.sample(docs)
    assert sampled.columns == docs.columns and sorted(r["doc_id"] for r in sampled.collect()) == kept


def test_mixing_spends_its_budget(spark):
    sf = SF.replace("0.001", "0.1")
    r = mixing.op4_raked_mixing(spark, sf).agg(F.sum("n_tokens").alias("all"), F.sum(F.when(F.col("kept"), F.col("n_tokens"))).alias("kept")).first()
    assert 0.75 < r["kept"] / r["all"] < 0.85


URLS = ["http://A.Example.NET/en/x?q#f", "https://net", "http://net/", "http://example.net/", "http://x.example.com/de/1", "http://example.com/de", "org/fr/", None, "", "http://deep.a.org/fr/", "http://notexample.net/en/", "ftp:///de/", "http://u@h.net:80/p", "http://example.net?en/", "x://y://net/"]


def brute_rule(url, rules, default="allow"):
    host = path = ""
    if url and "://" in url:
        rest = url.split("://", 1)[1]
        host = re.match(r"[^/?#]*", rest)[0]
        path = re.match(r"[^?#]*", rest[len(host) :])[0]
        host = re.sub("[A-Z]", lambda m: m[0].lower(), host)
    fits = [(len(h + p), len(h), h + p, v == "allow", v) for h, p, v in rules if host and (host == h or host.endswith("." + h)) and path.startswith(p)]
    best = max(fits, default=None)
    return host, path, best and best[2], best[4] if best else default


@pytest.mark.parametrize("rules", [url_rules.RULES, (("net", "/", "block"), ("a.net", "/", "allow"), ("b.a.net", "/x", "block"), ("net", "/x/y/z/long", "allow"), ("com", "", "block"))])
@pytest.mark.parametrize("partitions", [1, 5])
def test_urls_against_brute_force(spark, rules, partitions):
    rng = random.Random(9)
    hosts = ["net", "a.net", "b.a.net", "c.b.a.net", "xa.net", "example.com", "q.example.com", "org", "a-b.net", "a.net0"]
    urls = URLS + [f"http://{rng.choice(hosts)}{rng.choice(['', '/', '/x', '/x/y/z/longer', '/de/', '/fr/1', '?a'])}" for _ in range(120)] + ["http://hot.example.net/en/"] * 80
    pages = spark.createDataFrame([(i, u, "h", "clash") for i, u in enumerate(urls)], "page_id long, url string, html string, host string")
    got = {r["page_id"]: tuple(r[c] for c in ("host", "path", "rule", "verdict")) for r in url_rules.judge(pages, url_rules.rule_table(spark, rules), partitions=partitions).collect()}
    assert len(got) == len(urls)
    for i, u in enumerate(urls):
        assert got[i] == brute_rule(u, rules), u


def test_urls_without_rules_or_pages(spark):
    pages = spark.createDataFrame([(1, "http://a.net/")], "page_id long, url string")
    none = url_rules.rule_table(spark).where("false")
    assert url_rules.judge(pages, none).first()["verdict"] == "allow"
    assert url_rules.judge(pages.where("false"), url_rules.rule_table(spark)).count() == 0
