"""The SQL functions against the operators they stand for."""

from __future__ import annotations

import numpy as np
import pytest

from idfold import sqlsurface
from idfold.operators import baselines
from idfold.operators.kernel import FoldParams, fold_arrays


def test_vectors_and_auc(spark):
    sqlsurface.register(spark)
    spark.createDataFrame([(0, 0.1, [1.0, 2.0]), (1, 0.4, [3.0, 4.0]), (1, 0.1, None)], "label int, score double, v array<double>").createOrReplaceTempView("scored")
    assert spark.sql("SELECT auc(label, score) AS a FROM scored").first()["a"] == 0.75
    assert [r["d"] for r in spark.sql("SELECT vec_dot(v, v) AS d FROM scored ORDER BY score DESC, label").collect()] == [25.0, 5.0, None]
    assert spark.sql("SELECT vec_norm(v) AS n FROM scored ORDER BY score DESC").first()["n"] == 5.0


def test_fold_chain_table_function(spark):
    sqlsurface.register(spark)
    rng = np.random.default_rng(1)
    rows = [(f, i, float(rng.integers(0, 30)), int(rng.integers(0, 9))) for f in "ab" for i in range(30)]
    spark.createDataFrame(rows, "feature string, id bigint, value double, accesses bigint").createOrReplaceTempView("line")
    got = {(r["feature"], r["id"]): r["row"] for r in spark.sql("SELECT * FROM fold_chain(TABLE(line) PARTITION BY (feature), 5)").collect()}
    for f in "ab":
        mine = sorted((v, i, c) for g, i, v, c in rows if g == f)
        to, _, _ = fold_arrays(np.array([m[0] for m in mine]), np.array([m[2] for m in mine]), FoldParams(row_budget=5))
        assert all(got[f, m[1]] == k for m, k in zip(mine, to, strict=True))


def test_map_function(spark, monkeypatch):
    m = baselines.modulo(spark.createDataFrame([("f", i) for i in range(9)], "feature string, id bigint"), 4)
    sqlsurface.register_map(spark, m)
    assert [r[0] for r in spark.sql("SELECT fold_row('f', id) FROM range(7, 10) ORDER BY id").collect()] == [3, 0, None]
    monkeypatch.setattr(sqlsurface, "MAP_ENTRIES", 3)
    with pytest.raises(ValueError):
        sqlsurface.register_map(spark, m)
