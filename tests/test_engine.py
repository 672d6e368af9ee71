"""Both engines, maps, lookups, measures and the student, on small inputs."""

from __future__ import annotations

import numpy as np
import pytest
from pyspark.sql import functions as F

from idfold.functions.hashing import prehash, universal
from idfold.operators import access, baselines, chain, mapping, metrics
from idfold.operators.kernel import FREQUENCY_MODES, FoldParams, fold_arrays
from idfold.operators.student import ModelParams, auc, init_model, scatter_grad, score, train
from idfold.plans.ordering import with_next, with_positions


@pytest.fixture(scope="module")
def teacher_table(spark):
    rng = np.random.default_rng(3)
    rows = [("f", int(i), [float(rng.integers(0, 90)), float(rng.normal())], int(rng.zipf(1.6) % 1000)) for i in range(240)]
    return spark.createDataFrame(rows, "feature string, id bigint, vec array<double>, accesses bigint")


@pytest.fixture(scope="module")
def built(teacher_table):
    return chain.build(teacher_table).persist()


def plain(built, dim, p):
    rows = sorted((r["value"], r["id"], r["accesses"]) for r in built.where(F.col("dim") == dim).collect())
    row, clusters, trace = fold_arrays(np.array([r[0] for r in rows]), np.array([r[2] for r in rows]), p)
    return {r[1]: int(k) for r, k in zip(rows, row, strict=True)}, clusters, trace


def test_chain_positions(built):
    for d in (0, 1):
        got = built.where(F.col("dim") == d).orderBy("pos").collect()
        assert [r["pos"] for r in got] == list(range(1, 241))
        assert [(r["value"], r["id"]) for r in got] == sorted((r["value"], r["id"]) for r in got)


@pytest.mark.parametrize("mode", sorted(FREQUENCY_MODES))
def test_engines_agree_with_the_plain_fold(built, mode):
    p = FoldParams(row_budget=60, stride=70, size_cap=7, **FREQUENCY_MODES[mode])
    for engine in ("local", "distributed"):
        got = mapping.emit(built, chain.fold(built, p, engine=engine)).collect()
        for d in (0, 1):
            want, _, _ = plain(built, d, p)
            assert {r["id"]: r["row"] for r in got if r["slot"] == d} == want


@pytest.mark.parametrize("gates", [("bulk", "gap", "rarity"), ("gap", "rarity", "bulk"), ("rarity",), ("bulk",), ("bulk", "rarity"), ("rarity", "bulk", "gap")])
@pytest.mark.parametrize("cap", [1, 4])
def test_reordered_gates_agree(built, gates, cap):
    p = FoldParams(row_budget=120, stride=50, size_cap=cap, gates=gates)
    got = mapping.emit(built, chain.fold(built, p, engine="distributed")).where("slot = 0").collect()
    assert {r["id"]: r["row"] for r in got} == plain(built, 0, p)[0]


def test_leading_rows_with_many_ties(spark):
    """A prefix of the order (score, pos) of at least the width, and not the whole chain."""
    df = spark.range(20000).select(F.lit("f").alias("feature"), F.lit(0).alias("dim"), (F.col("id") + 1).alias("pos"), F.floor(F.col("id") % 10 / 9).cast("double").alias("gap"), F.lit(200).alias("r"))
    got = sorted((r["gap"], r["pos"]) for r in chain.leading(df, "gap", "pos", F.col("r")).collect())
    want = sorted((r["gap"], r["pos"]) for r in df.collect())
    assert 200 <= len(got) < 600 and got == want[: len(got)]
    assert chain.leading(df, "gap", "pos", F.lit(10**6)).count() == 20000


def test_result_does_not_depend_on_partitions(teacher_table):
    p = FoldParams(row_budget=50, stride=20, size_cap=8)
    maps = []
    for n in (1, 3, 7):
        c = chain.build(teacher_table.repartition(n))
        maps.append({(r["slot"], r["id"]): r["row"] for r in mapping.emit(c, chain.fold_local(c, p)).collect()})
    assert maps[0] == maps[1] == maps[2]


def test_emission_both_ways(built):
    cuts = chain.fold_local(built, FoldParams(row_budget=30, stride=10)).persist()
    assert sorted(mapping.emit(built, cuts).collect()) == sorted(mapping.emit_range_join(built, cuts).collect())
    assert cuts.agg(F.sum("size")).first()[0] == 480


def test_no_single_partition_on_chains(built):
    plan = with_next(built, ["feature", "dim"], ["value"])._jdf.queryExecution().executedPlan().toString()
    assert "SinglePartition" not in plan


def test_next_row_across_blocks(spark):
    df = spark.range(25).select(F.lit("f").alias("k"), (F.col("id") + 1).alias("pos"), (F.col("id") * 3).alias("v"))
    got = {r["pos"]: r["next_v"] for r in with_next(df, ["k"], ["v"], block=4).collect()}
    assert got == {i: (i * 3 if i < 25 else None) for i in range(1, 26)}


def test_positions_within_groups(spark):
    df = spark.createDataFrame([(g, v) for g in "ab" for v in range(50)], "g string, v int")
    got = with_positions(df, ["v"], within=["g"], partitions=7).collect()
    assert all(r["pos"] == r["v"] + 1 for r in got)


def test_lookup_sum_and_concat(spark):
    m = spark.createDataFrame([("f", s, i, (i + s) % 2) for s in (0, 1) for i in range(4)], "feature string, slot int, id bigint, row bigint")
    t = spark.createDataFrame([("f", s, r, [float(10 * s + r), 1.0]) for s in (0, 1) for r in (0, 1)], "feature string, slot int, row bigint, vec array<double>")
    ids = spark.createDataFrame([(1, "f", 0), (1, "f", 1), (2, "f", 3)], "sample_id bigint, feature string, id bigint")
    got = {r["sample_id"]: r["vec"] for r in mapping.lookup(ids, m, t, slots=2, combine="sum").collect()}
    assert got == {1: [22.0, 4.0], 2: [11.0, 2.0]}
    wide = {r["sample_id"]: r["vec"] for r in mapping.lookup(ids, m, t, slots=2, combine="concat").collect()}
    assert wide == {1: [1.0, 2.0, 21.0, 2.0], 2: [1.0, 1.0, 10.0, 1.0]}


def test_salted_lookup_equals_plain(spark):
    ids = spark.createDataFrame([("f", i % 5, i) for i in range(200)], "feature string, id bigint, n int")
    m = baselines.modulo(spark.createDataFrame([("f", i) for i in range(5)], "feature string, id bigint"), 3)
    hot = spark.createDataFrame([("f", 0)], "feature string, id bigint")
    a = mapping.apply(ids, m).select("n", "row").collect()
    assert sorted(a) == sorted(mapping.apply_salted(ids, m, hot=hot).select("n", "row").collect())


def test_unseen_ids_are_hashed_into_range(spark):
    got = spark.createDataFrame([(-5,), (3,), (99,), (100,), (10**12,)], "id bigint").select("id", prehash(F.col("id"), 100).alias("h")).collect()
    assert all(0 <= r["h"] < 100 for r in got) and got[1]["h"] == 3 and got[2]["h"] == 99


def test_plan_and_sizes(spark):
    h = spark.createDataFrame([("a", 100), ("b", 1000)], "feature string, height bigint")
    got = {r["feature"]: r for r in mapping.plan(h, size_pct=10, skip_below=500, slots=2).collect()}
    assert not got["a"]["folded"] and got["a"]["total_rows"] == 100
    assert got["b"]["rows_per_slot"] == 50 and got["b"]["total_rows"] == 100
    each = {r["feature"]: r for r in mapping.plan(h, size_pct=10, skip_below=0, slots=2, budget_mode="each").collect()}
    assert each["b"]["total_rows"] == 200


def test_save_and_load(spark, tmp_path):
    m = baselines.modulo(spark.createDataFrame([("f", i) for i in range(9)], "feature string, id bigint"), 4)
    mapping.save(m, str(tmp_path / "m"), version="a")
    mapping.save(m.withColumn("row", F.col("row") + 1), str(tmp_path / "m"), version="b")
    assert sorted(mapping.load(spark, str(tmp_path / "m"), version="a").collect()) == sorted(m.collect())


def test_retention_shifts_the_rest(spark):
    counts = spark.createDataFrame([("f", i, 100 - i) for i in range(40)], "feature string, id bigint, accesses bigint")
    kept = baselines.kept_rows(counts, 10.0)
    folded = baselines.modulo(counts, 3)
    got = {r["id"]: r["row"] for r in mapping.retain(counts, folded, kept=kept).collect()}
    assert [got[i] for i in range(4)] == [0, 1, 2, 3] and got[4] == 4 + 4 % 3 and len(got) == 40


def test_zero_use_ids_are_counted(spark):
    s = spark.createDataFrame([(1, [5, 5, 6]), (2, [6])], "sample_id bigint, f array<bigint>")
    vocab = spark.createDataFrame([("f", i) for i in (5, 6, 7)], "feature string, id bigint")
    assert {r["id"]: r["accesses"] for r in access.count(s, features=["f"], vocab=vocab).collect()} == {5: 2, 6: 2, 7: 0}


def pairs_auc(label, value):
    pos, neg = value[label == 1], value[label == 0]
    return float(np.mean([(p > n) + 0.5 * (p == n) for p in pos for n in neg]))


def test_auc_equals_counting_pairs(spark):
    rng = np.random.default_rng(5)
    label, value = rng.integers(0, 2, 80), rng.integers(0, 9, 80).astype(float)
    want = pairs_auc(label, value)
    assert abs(auc(label, value) - want) < 1e-12
    df = spark.createDataFrame([(int(a), float(b)) for a, b in zip(label, value, strict=True)], "label int, score double")
    assert abs(metrics.auc(df).first()["auc"] - want) < 1e-6
    assert metrics.auc(df.withColumn("score", F.lit(1.0))).first()["auc"] == 0.5
    assert metrics.auc(df.where("label = 1")).first()["auc"] is None and auc(np.ones(3), np.ones(3)) is None


def test_student_learns_and_repeats():
    rng = np.random.default_rng(1)
    ids = rng.integers(0, 20, 2000)
    label = (ids % 2).astype(int)
    p = ModelParams(epochs=6, batch=128)
    out = []
    for _ in range(2):
        model = init_model([20], p)
        train(model, [[[i] for i in ids]], label, np.ones(len(ids)), p)
        out.append(score(model, [[[i] for i in range(20)]]))
    assert (out[0] == out[1]).all()
    assert auc(np.arange(20) % 2, out[0]) > 0.95


def test_gradient_expansion():
    g = np.array([[1.0, 2.0, 3.0, 4.0], [10.0, 20.0, 30.0, 40.0]])
    assert scatter_grad(g, np.array([1, 1]), 2, "sum", 0, 2).tolist() == [[0, 0, 0, 0], [11, 22, 33, 44]]
    assert scatter_grad(g, np.array([0, 1]), 2, "concat", 1, 2).tolist() == [[3, 4], [30, 40]]


def test_quotient_remainder_separates_all_ids(spark):
    v = spark.createDataFrame([("f", i) for i in range(50)], "feature string, id bigint")
    m = baselines.quotient_remainder(v, 7).groupBy("id").agg(F.array_sort(F.collect_list(F.struct("slot", "row"))).alias("k"))
    assert m.select("k").distinct().count() == 50


def test_hash_stays_portable(spark):
    got = spark.range(5).select(universal(F.col("id"), 1000, 1).alias("h")).collect()
    assert [r["h"] for r in got] == [((i * 69621 + 7368787) % 2147483647) % 1000 for i in range(5)]
