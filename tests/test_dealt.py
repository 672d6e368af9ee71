"""Training from the one shared copy of the samples: all of them every pass, no shuffle and no file per task."""

from __future__ import annotations

import numpy as np
import pytest
from pyspark.sql import functions as F

from idfold.catalog import workloads
from idfold.operators import dealt, sample_file, student, teacher
from idfold.sources import samples as src
from tests.conftest import SF


@pytest.fixture
def small_blocks(monkeypatch):
    for module in (dealt, sample_file, teacher, workloads):
        monkeypatch.setattr(module, "BLOCK", 1000)


def dealt_range(spark, n=5000):
    rows = spark.range(n).select("id", (F.col("id") % 7).alias("a"), (F.col("id") % 2).alias("label"), F.when(F.col("id") % 9 > 0, (F.col("id") % 9).cast("int")).alias("day"))
    return dealt.deal(rows, x=[F.col("id"), F.col("a")], label=F.col("label"), day=F.col("day"), key=[F.col("id")], n=n)


def test_every_pass_gives_all_samples_without_a_shuffle(spark, small_blocks):
    held, kind = dealt_range(spark), dealt.kind(2)
    top = held.agg(F.sum("n"), F.sum("early"), F.max(F.get("top", F.lit(0)))).first()
    assert tuple(top) == (5000, sum(0 < i % 9 < 8 for i in range(5000)), 4999)
    streams = [dealt.in_one(dealt.passes(held, range(3 * k, 3 * k + 3))) for k in range(5)]
    both = dealt.beside(streams)
    assert "Exchange" not in both._jdf.queryExecution().executedPlan().toString()
    seen = {}

    def run(batches):
        import pyarrow as pa
        from pyspark import TaskContext

        for step, stream in dealt.by_group(batches, "step"):
            s = np.concatenate([dealt.records(b["samples"], kind) for b in stream])
            day = np.where(s["x"][:, 0] % 9 > 0, s["x"][:, 0] % 9, dealt.NO_DAY)
            right = sorted(s["x"][:, 0]) == list(range(5000)) and (s["x"][:, 1] == s["x"][:, 0] % 7).all() and (s["y"] == s["x"][:, 0] % 2).all() and (s["day"] == day).all()
            yield pa.RecordBatch.from_pylist([{"task": TaskContext.get().partitionId(), "step": int(step), "right": bool(right)}])

    for r in both.mapInArrow(run, "task long, step long, right boolean").collect():
        assert r["right"]
        seen.setdefault(r["task"], []).append(r["step"])
    assert sorted(seen.values()) == [[3 * k, 3 * k + 1, 3 * k + 2] for k in range(5)]


def test_order_models_train_from_the_shared_copy(spark, small_blocks, monkeypatch):
    class NoFile(sample_file.SampleFile):
        def add(self, x, y, w=1):
            raise AssertionError("samples of a large set went to a file of the task")

    monkeypatch.setattr(workloads, "SampleFile", NoFile)
    o = workloads.Orders(spark, SF)
    assert o.early > 1000 and o.heights == {"part": 200, "customer": 150, "supplier": 10, "nation": 25}
    got = {r["cell"]: r for r in o.run([o.cell("full", "full", 100), o.cell("modulo_10", "modulo", 10)], epochs=12).collect()}
    days = dict(src.order_samples(spark, SF).groupBy((F.col("day") < 8).alias("early")).count().collect())
    assert all(r["train_uses"] == days[True] and r["eval_uses"] == days[False] and r["reps"] == 2 for r in got.values())
    assert got["full"]["mean_auc"] > 0.6 > got["modulo_10"]["mean_auc"] > 0.4


def test_the_teacher_trains_from_the_shared_copy(spark, small_blocks):
    rows = spark.range(3000).select(F.col("id").alias("sample_id"), (F.col("id") % 12).alias("a"), F.array(F.col("id") % 7, (F.col("id") + 3) % 7).alias("b"), (F.col("id") % 3 == 0).cast("int").alias("label"))
    got = teacher.deep(rows, features=["a", "b"], heights={"a": 12, "b": 7}, epochs=3, batch=64).collect()
    assert len(got) == 19 and all(r["accesses"] == (250 if r["feature"] == "a" else sum(x % 7 == r["id"] or (x + 3) % 7 == r["id"] for x in range(3000))) for r in got)
    of = {r["id"]: np.array(r["vec"]) for r in got if r["feature"] == "a"}
    assert np.linalg.norm(of[0] - of[3]) < np.linalg.norm(of[0] - of[1])


def test_streamed_epochs_take_every_sample_once(monkeypatch):
    monkeypatch.setattr(sample_file, "BLOCK", 500)
    n, kind, sizes = 3100, dealt.kind(1), []
    samples = np.zeros(n, dtype=kind)
    samples["x"][:, 0] = np.arange(n)
    p, real = student.ModelParams(epochs=2), sample_file.train_batch
    monkeypatch.setattr(sample_file, "train_batch", lambda m, c, label, weight, q: (sizes.append(c[0][:, 0]), real(m, c, label, weight, q)))
    epoch = sample_file.Streamed(student.init_model([n], p), n, p, columns=lambda s: [s["x"].astype(np.int64)])
    for _ in range(2):
        for k in range(0, n, 70):
            epoch.add(samples[k : k + 70])
        epoch.end()
    ids = np.concatenate(sizes)
    assert sorted(ids[:n]) == sorted(ids[n:]) == list(range(n)) and max(map(len, sizes)) == p.batch_of(n)
