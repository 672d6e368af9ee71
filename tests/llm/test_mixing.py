"""Raking under the bound: both forms against NumPy, shares against targets, odd inputs."""

from __future__ import annotations

import numpy as np
import pytest
from pyspark.sql import functions as F

from idfold.llm import mixing

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


@pytest.fixture(scope="module")
def docs(spark, tmp_path_factory):
    rows = [(i, "word " * 20, "en" if i % 10 else "de", "a" if i % 3 else "b", 0) for i in range(3000)]
    path = str(tmp_path_factory.mktemp("mix") / "d")
    spark.createDataFrame(rows, SCHEMA).write.parquet(path)
    return spark.read.parquet(path)


def test_expected_shares_meet_feasible_targets(spark, docs):
    """A rare value takes its bound and is taken whole; the other shares are met."""
    targets = {"source": spark.createDataFrame([("a", 0.6), ("b", 0.4)], "source string, share double"), "lang": spark.createDataFrame([("en", 0.8), ("de", 0.2)], "value string, share double")}
    report = {(r["margin"], r["value"]): r for r in mixing.margins(docs, targets=targets).collect()}
    assert report["lang", "de"]["feasible"] == pytest.approx(0.125) and report["lang", "de"]["target"] == pytest.approx(0.2)
    for r in report.values():
        assert r["expected"] == pytest.approx(r["feasible"], abs=1e-5) and abs(r["residual"]) < 1e-5
    drawn = mixing.sample(docs, targets=targets)
    n = drawn.count()
    assert abs(n / 3000 - 0.8) < 0.03
    assert abs(drawn.where("source = 'b'").count() / n - 0.4) < 0.03 and drawn.where("lang = 'de'").count() == 300
    expected = mixing.mix(docs, targets=targets).agg((F.sum(F.when(F.col("source") == "b", F.col("probability"))) / F.sum("probability")).alias("s")).first()["s"]
    assert expected == pytest.approx(0.4, abs=1e-5)


def plain(cells, goals, want, budget, rounds):
    """The same raking cell by cell."""
    tokens = np.array([c[3] for c in cells], dtype=float)
    free = tokens * budget
    for _ in range(rounds):
        for m in range(3):
            for value, goal in goals[m].items():
                at = np.array([c[m] == value for c in cells])
                held, now, g = tokens[at].sum(), np.minimum(tokens, free)[at].sum(), goal * want
                over = at & (free >= tokens)
                if g >= held * (1 - 1e-12):
                    free[at] = np.maximum(free, tokens)[at]
                elif g >= now:
                    loose = free[at & ~over].sum()
                    free[at] *= max((g - tokens[over].sum()) / loose, 1.0) if loose > 0 else 1.0
                else:
                    free[at] *= g / now if now > 0 else 0.0
    return np.minimum(tokens, free)


def test_fold_and_windows_agree_with_plain_raking(spark, tmp_path):
    draw = np.random.default_rng(3)
    rows = [(f"s{i}", f"l{j}", f"t{k}", int(draw.pareto(1.0) * 100)) for i in range(6) for j in range(3) for k in range(2) if draw.random() < 0.8]
    spark.createDataFrame(rows, "source string, lang string, topic string, tokens long").write.parquet(str(tmp_path / "c"))
    cells = spark.read.parquet(str(tmp_path / "c"))
    folded, goals = mixing.rake(cells, rounds=3)
    windowed, _ = mixing.rake(cells, rounds=3, fold_cells=0)
    goal = [{r["value"]: r["goal"] for r in goals.where(F.col("margin") == m).collect()} for m in mixing.MARGINS]
    want = 0.8 * sum(r[3] for r in rows)
    expected = {r[:3]: w for r, w in zip(rows, plain(rows, goal, want, 0.8, 3), strict=True)}
    for found in (folded, windowed):
        got = {(r["source"], r["lang"], r["topic"]): r["weight"] for r in found.collect()}
        assert got.keys() == expected.keys()
        for key, w in expected.items():
            assert got[key] == pytest.approx(w, rel=1e-9, abs=1e-9)


def test_odd_tables(spark, docs):
    assert mixing.sample(docs.where("false")).count() == 0 and mixing.mix(docs.where("false")).count() == 0
    rows = [(None, None, None, None, 1, 2), (None, None, None, None, 1, 2), (1, "", "en", "a", 0, 3)]
    odd = spark.createDataFrame(rows, SCHEMA + ", `weight.cell` int").withColumn("draw", F.lit(1)).withColumn("probability", F.lit("x"))
    kept = mixing.sample(odd, budget=1.0)
    assert kept.columns == odd.columns and kept.count() == 3
    assert mixing.mix(odd).count() == 3
