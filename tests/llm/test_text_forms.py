"""SentencePiece lattice, WARC derivatives and the pipeline."""

from __future__ import annotations

import glob
import gzip
import json
import random

import pytest
from pyspark.sql import functions as F

from idfold.llm import piece_lattice, queries, warc_derive
from tests.conftest import SF

TEXTS = [None, "", " ", "a", "Hello  wörld\n\nfoo \t bar", "▁x ▁", "ﷺ 日本語 😀 é x́", "ab" * 100 + " end", "nul \0 and\rcr", "\n", "thenation thenation, the", " lead", "trail "]


@pytest.fixture(scope="module")
def pieces():
    return piece_lattice.load_pieces()


@pytest.fixture(scope="module")
def model():
    import sentencepiece

    return sentencepiece.SentencePieceProcessor(model_file=piece_lattice.MODEL_PATH)


@pytest.mark.parametrize("hot", [0, 3, 1 << 20])
def test_encoding_equals_the_library(spark, pieces, model, hot):
    rng = random.Random(2)
    alphabet = ["the", "ing", " ", "  ", "\n", "é", "▁", "x", ").", "日", "\t", "😀", "#", "tion"]
    texts = TEXTS + ["".join(rng.choice(alphabet) for _ in range(rng.randrange(40))) for _ in range(150)]
    docs = spark.createDataFrame([(i, t, "clash", 1) for i, t in enumerate(texts)], "doc_id long, text string, ids string, n_tokens int")
    got = {r["doc_id"]: r for r in piece_lattice.encode(docs, pieces, hot=hot).collect()}
    assert len(got) == len(texts)
    for i, t in enumerate(texts):
        want = model.encode(t or "")
        assert got[i]["ids"] == want and got[i]["n_tokens"] == len(want), t
        assert got[i]["exact"] == ("▁" not in (t or ""))


def test_decoding_gives_the_text_back(spark, pieces, model):
    docs = spark.createDataFrame([(i, t) for i, t in enumerate(TEXTS)], "doc_id long, text string")
    tokens = piece_lattice.encode(docs, pieces).select("doc_id", "ids")
    for r in piece_lattice.decode(tokens, pieces).collect():
        t = TEXTS[r["doc_id"]] or ""
        assert r["text"] == t.replace("▁", " ") == model.decode(r["ids"]) or "▁" in t
    assert piece_lattice.decode(tokens.withColumn("ids", F.lit(None).cast("array<int>")), pieces).first()["text"] is None


def test_empty_table(spark, pieces):
    assert piece_lattice.encode(spark.createDataFrame([], "doc_id long, text string"), pieces).count() == 0


def test_viterbi_fold_finds_the_best_path(spark, pieces):
    """The unigram fold against a plain Viterbi over the same pieces."""
    import dataclasses

    scores = {p: -len(p) ** 0.5 - (pieces.ids[p] % 7) / 10 for p in pieces.ids}
    uni = dataclasses.replace(pieces, kind="unigram", scores=scores)
    lowest = min(scores.values()) - 10
    words = [" thenation", "ing", "x日", "   ", " a", "unbelievable,"]
    got = {r["seg"]: r["ids"] for r in piece_lattice.encode_segments(spark.createDataFrame([(w,) for w in words], "seg string"), uni).collect()}
    for w in words:
        best = [(0.0, [])]
        for e in range(1, len(w) + 1):
            options = []
            for s in range(max(0, e - uni.longest), e):
                p = w[s:e]
                if p in uni.ids:
                    options.append((best[s][0] + scores[p], best[s][1] + [uni.ids[p]]))
                elif e - s == 1:
                    options.append((best[s][0] + lowest, best[s][1] + [uni.byte_base + b for b in p.encode()]))
            best.append(max(options, key=lambda o: o[0]))
        assert got[w] == best[-1][1], w


PAGES = [
    (1, "http://a.net/x", "<html><head><title>T &amp; U</title><script>var x='</p>';</script></head><body><p>One<br>two</p><!-- no --><a href='/l?a=1&amp;b'>go</a></body></html>"),
    (2, None, None),
    (3, "u", ""),
    (3, "u", ""),
    (4, "http://b/", "plain < 3 and > 2 text"),
    (5, "http://c/", "<p>" + "long " * 50000 + "</p>"),
]


def test_records_link_and_keep_digests(spark):
    pages = spark.createDataFrame([(*p, "clash") for p in PAGES], "page_id long, url string, html string, block string")
    responses = {r["page_id"]: r for r in warc_derive.response_records(pages).collect()}
    got = warc_derive.derivatives(pages).collect()
    assert len(got) == 2 * len(PAGES)
    for r in got:
        source = responses[r["page_id"]]
        assert r["refers_to"] == source["record_id"] and r["payload_digest"] == source["payload_digest"] and r["target_uri"] == source["target_uri"]
        assert r["warc_date"] == source["warc_date"] and r["source_headers"] == source["source_headers"]
        assert r["block_digest"] == warc_derive.digest(r["block"].encode()) and r["content_length"] == len(r["block"].encode())
    text = {r["page_id"]: r["block"] for r in got if r["warc_type"] == "conversion"}
    assert text[1] == "T & U\nOne\ntwo\ngo" and text[2] == "" and text[4] == "plain < 3 and > 2 text"
    facts = json.loads(next(r["block"] for r in got if r["page_id"] == 1 and r["warc_type"] == "metadata"))
    assert facts["Links"] == ["/l?a=1&b"] and facts["Title"] == "T & U"
    assert len({r["record_id"] for r in got}) == 2 * (len(PAGES) - 1)


def test_warc_files_parse_back(spark, tmp_path):
    pages = spark.createDataFrame(PAGES, "page_id long, url string, html string")
    records = warc_derive.derivatives(pages)
    warc_derive.write_warc(records, str(tmp_path / "w"))
    back = [r for f in glob.glob(f"{tmp_path}/w/*.gz") for r in warc_derive.parse(gzip.open(f).read())]
    want = sorted((r["record_id"], r["refers_to"], r["block"]) for r in records.collect())
    assert sorted((r["WARC-Record-ID"], r["WARC-Refers-To"], r["block"].decode()) for r in back) == want
    row = records.first().asDict()
    assert warc_derive.parse(warc_derive.serialised(row))[0]["block"].decode() == row["block"]


@pytest.mark.parametrize("name", sorted(queries.ORACLES))
def test_against_duckdb(spark, duck, same, name):
    same(queries.QUERIES[name](spark, SF).toPandas(), duck.execute(queries.ORACLES[name]).df())


def test_pipeline_stages(spark, model, tmp_path):
    import corpus_pipeline

    docs = spark.read.parquet(f"{SF}/documents.parquet")
    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality_classifier", "exact_dedup", "simhash_near_dedup", "mixing", "sentencepiece"]
    seen = docs.count()
    for k, (name, stage) in enumerate(corpus_pipeline.STAGES[:-1]):
        before = docs
        stage(spark, docs, SF).write.parquet(str(tmp_path / name))
        docs = spark.read.parquet(str(tmp_path / name))
        assert docs.columns == before.columns and 0 < docs.count() <= seen, name
        seen = docs.count()
    texts = {r["doc_id"]: r["text"] for r in docs.collect()}
    out = corpus_pipeline.run(spark, SF).collect()
    assert {r["doc_id"] for r in out} == set(texts)
    assert all(r["ids"] == model.encode(texts[r["doc_id"]]) for r in out)
