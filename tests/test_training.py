"""Trained teachers, synchronous training, exact samples and the scores behind an AUC."""

from __future__ import annotations

import numpy as np
import pytest
from pyspark.sql import functions as F

from idfold.operators import metrics, student, teacher
from idfold.plans import experiments, synchronous
from idfold.sources import samples as src


def logs(spark, n: int = 300):
    draw = np.random.default_rng(5)
    a, b = draw.integers(0, 12, n), draw.integers(0, 7, n)
    label = ((a % 3 + b % 2 + draw.random(n)) > 2).astype(int)
    rows = [(int(i), int(x), [int(y), int((y + 3) % 7)], int(z)) for i, (x, y, z) in enumerate(zip(a, b, label, strict=True))]
    return spark.createDataFrame(rows, "sample_id long, a long, b array<long>, label int"), rows


def test_synchronous_steps_equal_numpy(spark):
    """Two steps over all samples, spread over partitions, against the same two steps in one array."""
    df, rows = logs(spark)
    p = student.ModelParams(width=2, seed=3)
    tables, model = synchronous.train(df.repartition(3), features=["a", "b"], params=p, steps=2)
    start = synchronous.start_tables(df.select(F.posexplode(F.array(F.array("a"), "b")).alias("k", "ids")).select("k", F.explode("ids").alias("id")), 2, p)
    local = {"tables": [np.zeros((12, 2)), np.zeros((7, 2))], "acc": [np.zeros(12), np.zeros(7)], "moments": None, "t": 0}
    for r in start.collect():
        local["tables"][r["k"]][r["id"]] = r["vec"]
    local["dense"] = student.init_dense(2, p, np.random.default_rng(p.seed))
    columns = [np.array([[r[1]] for r in rows]), np.array([r[2] for r in rows])]
    for _ in range(2):
        student.train_batch(local, columns, np.array([r[3] for r in rows]), np.ones(len(rows)), p)
    for r in tables.collect():
        assert r["vec"] == pytest.approx(list(local["tables"][r["k"]][r["id"]]), rel=1e-9, abs=1e-12)
        assert r["accesses"] == sum(int((columns[r["k"]] == r["id"]).sum(axis=1)[i]) for i in range(len(rows)))
    for got, want in zip(model["dense"], local["dense"], strict=True):
        assert np.allclose(got, want)


def test_training_learns_and_counts(spark):
    df, rows = logs(spark)
    single = df.select("sample_id", "label", F.array("a").alias("ids"))
    vocab = spark.createDataFrame([(i,) for i in range(14)], "id long")
    got = {r["id"]: r for r in teacher.click(single, feature="a", vocab=vocab, width=2).collect()}
    assert set(got) == set(range(14)) and got[13]["accesses"] == 0
    assert all(got[i]["accesses"] == sum(r[1] == i for r in rows) for i in range(12))
    model = student.init_model([12], student.ModelParams(epochs=30))
    columns, label = [np.array([[r[1]] for r in rows])], np.array([r[3] for r in rows])
    before = student.auc(label, student.score(model, columns))
    student.train(model, columns, label, np.ones(len(rows)), student.ModelParams(epochs=30))
    assert student.auc(label, student.score(model, columns)) > max(0.6, before)
    assert np.abs(student.quantized(model["tables"][0], 8) - model["tables"][0]).max() <= np.abs(model["tables"][0]).max() / 127


def test_lists_and_arrays_train_alike():
    """Bags as lists of lists and as arrays take the same steps."""
    p = student.ModelParams(seed=1)
    ids, label = np.array([[0, 1], [2, 2], [1, 0]]), np.array([1, 0, 1])
    models = [student.init_model([3], p) for _ in range(2)]
    student.train_batch(models[0], [ids], label, np.ones(3), p)
    student.train_batch(models[1], [ids.tolist()], label, np.ones(3), p)
    assert np.allclose(models[0]["tables"][0], models[1]["tables"][0])
    grad = np.arange(8.0).reshape(2, 4)
    assert np.allclose(student.scatter_grad(grad, np.array([1, 1]), 2), [[0] * 4, grad.sum(0)])
    assert np.allclose(student.scatter_grad(grad, np.array([0, 1]), 2, "concat", 1, 2), grad[:, 2:])


@pytest.mark.parametrize("n", [0, 1, 500, 999, 1000, 2000])
def test_exact_samples_without_a_global_sort(spark, n):
    df = spark.range(1000).select(F.col("id").alias("sample_id"))
    got = sorted(r[0] for r in src.take(df, n, seed=4).collect())
    hashed = df.select("sample_id", F.xxhash64("sample_id", F.lit(4)).alias("h")).collect()
    assert got == sorted(r[0] for r in sorted(hashed, key=lambda r: (r["h"], r["sample_id"]))[:n])


def test_scores_give_the_reported_auc(spark, duck):
    """The AUC of a cell equals that of its emitted scores, in Spark and in DuckDB."""
    draw = np.random.default_rng(6)
    rows = [(part, int(i), int(y), int(draw.integers(1, 5))) for part in ("train", "8") for i in range(40) for y in (0, 1) if draw.random() < (0.3 + 0.6 * ((i % 4 == y) or i % 4 > 1))]
    data = spark.createDataFrame(rows, "part string, id long, label int, uses long")
    maps = spark.createDataFrame([(c, 0, i, i % m) for c, m in (("full", 40), ("modulo_4", 4)) for i in range(40)], "cell string, slot int, id long, row long")
    told = {r["cell"]: r["auc"] for r in experiments.run_cells(data, maps, reps=1).collect()}
    scores = experiments.run_scores(data, maps)
    assert told == pytest.approx({r["cell"]: r["auc"] for r in metrics.auc(scores, keys=["cell"], weight="uses").collect()}, abs=1e-6)
    frame = scores.toPandas()  # noqa: F841 (read by DuckDB)
    sql = """SELECT a.cell, sum(CASE WHEN a.score > b.score THEN 1.0 WHEN a.score = b.score THEN 0.5 ELSE 0 END * a.uses * b.uses) / sum(a.uses * b.uses)
             FROM frame a JOIN frame b ON a.cell = b.cell AND a.label = 1 AND b.label = 0 GROUP BY a.cell"""
    import duckdb

    assert told == pytest.approx(dict(duckdb.sql(sql).fetchall()), abs=1e-9)
    delta = experiments.report(experiments.run_cells(data, maps, reps=1)).collect()
    assert {r["cell"]: r["delta_full"] for r in delta}["full"] == 0.0


@pytest.mark.parametrize("more", [{}, {"split": "pack", "size_cap": 4, "value_rule": "count_weighted"}])
def test_engines_agree_with_defaults(spark, more):
    """Both engines resolve what is left out per chain, pack alike and end."""
    from idfold.operators import chain
    from idfold.operators.kernel import FoldParams

    draw = np.random.default_rng(8)
    rows = [("f", int(i), [float(x), float(-x * y)], int(c)) for i, (x, y, c) in enumerate(zip(draw.normal(size=60).round(2), draw.normal(size=60).round(2), draw.integers(0, 9, 60), strict=True))]
    rows += [("g", i, [float(i % 7), float(i)], i) for i in range(25)]
    c = chain.build(spark.createDataFrame(rows, "feature string, id long, vec array<double>, accesses long"))
    p = FoldParams(row_budget=20, stride=25, **more)
    columns = ["feature", "dim", "row", "lo_pos", "hi_pos", "size", "accesses"]
    local, spread = (sorted(tuple(r[k] for k in columns) for r in chain.fold(c, p, engine=e).collect()) for e in ("local", "distributed"))
    assert local == spread and {r[0] for r in local} == {"f", "g"}
