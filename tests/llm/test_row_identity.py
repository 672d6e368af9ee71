"""Row numbers stay with their rows whatever the number of tasks, and operators that join by them with them."""

from __future__ import annotations

import pytest
from pyspark.sql import functions as F

from idfold.llm import exact_dedup, line_dedup, shingle_dedup, weak_quality
from idfold.llm.common import ROW_UID, as_scan, join_split, with_row_uid
from tests.conftest import SF


@pytest.fixture
def many_files(spark, tmp_path):
    """The documents as six files of small row groups, twice over."""
    docs = spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text", "lang", "source")
    docs.unionByName(docs).repartition(6).write.option("parquet.block.size", 4096).parquet(str(tmp_path / "d"))
    return spark.read.parquet(str(tmp_path / "d"))


def _with_tasks(spark, n, f):
    spark.conf.set("spark.sql.files.maxPartitionBytes", str(n))
    try:
        return f()
    finally:
        spark.conf.unset("spark.sql.files.maxPartitionBytes")


def test_numbers_follow_rows(spark, many_files):
    numbers = [_with_tasks(spark, n, lambda: sorted((r[ROW_UID], r["doc_id"]) for r in with_row_uid(many_files).select(ROW_UID, "doc_id").collect())) for n in (20_000, 100_000_000)]
    assert numbers[0] == numbers[1] and len({n for n, _ in numbers[0]}) == many_files.count()
    with pytest.raises(ValueError):
        with_row_uid(many_files.withColumn(ROW_UID, F.lit(1)))


def test_results_do_not_depend_on_splits(spark, many_files):
    """Built under one setting of splits, run under another."""
    for keep in (exact_dedup.keep_winners, shingle_dedup.keep_first):
        built = _with_tasks(spark, 20_000, lambda keep=keep: keep(many_files))
        kept = _with_tasks(spark, 100_000_000, lambda built=built: sorted(r["doc_id"] for r in built.collect()))
        assert len(kept) == len(set(kept)) and kept == sorted(r["doc_id"] for r in keep(many_files).collect())
    lines = _with_tasks(spark, 20_000, lambda: line_dedup.dedup_lines(many_files, every_line=True))
    first = _with_tasks(spark, 100_000_000, lambda: {(r["doc_id"], r["n_lines"], r["n_removed"]) for r in lines.collect()})
    assert first == {(r["doc_id"], r["n_lines"], r["n_removed"]) for r in line_dedup.dedup_lines(many_files, every_line=True).collect()}


def test_copies_take_one_place_in_the_sample(spark):
    """A text copied many times weighs in the training sample like any other."""
    texts = [f"this is plain text number {i} with several ordinary words in it" for i in range(30)]
    once = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "doc_id long, text string")
    often = once.unionByName(spark.createDataFrame([(100 + i, texts[0]) for i in range(300)], "doc_id long, text string"))
    assert weak_quality.fit(often, train_texts=1000) == pytest.approx(weak_quality.fit(often, train_texts=30), abs=1e-9)


def test_hot_keys_join_by_broadcast(spark):
    rows = as_scan(spark.createDataFrame([(i % 7 if i < 900 else 3, i) for i in range(2000)] + [(None, 1)], "k long, x long"))
    heads = as_scan(rows.where("k is not null").groupBy("k").agg(F.count("*").alias("n")))
    got = join_split(rows, heads, "k", count="n", hot_share=0.2)
    assert sorted((r["k"], r["x"]) for r in got.collect()) == sorted((r["k"], r["x"]) for r in rows.collect() if r["k"] is not None)
