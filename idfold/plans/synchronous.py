"""Synchronous training of one click model over a cluster.

Tables stay DataFrames (feature number, id, vec, acc); a step joins them to the samples, computes
gradients per partition with the formulas of ``idfold.operators.student``, sums them per table row
by an ordinary aggregate and writes the next tables out. The driver holds the dense layers only, a
few hundred numbers. Every step uses all samples, so that its result does not depend on how they are
partitioned.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from idfold.operators.student import ModelParams, backward, dense_step, init_dense
from idfold.storage import settle


def start_value(feature: int, width: int, seed: int):
    """Starting entries of an id, uniform in -0.1 .. 0.1, from a hash of feature, id and place."""
    unit = lambda j: F.pmod(F.xxhash64(F.lit(feature), F.col("id"), F.lit(j), F.lit(seed)), F.lit(1 << 20)) / F.lit(float(1 << 20))
    return F.array(*[(unit(j) - 0.5) * 0.2 for j in range(width)])


def start_tables(long: DataFrame, features: int, p: ModelParams) -> DataFrame:
    """(k, id, vec, acc, accesses) of every id in ``long(k, id)``, with its uses."""
    uses = long.groupBy("k", "id").agg(F.count("*").alias("accesses"))
    vec = F.lit(None)
    for k in range(features):
        vec = F.when(F.col("k") == k, start_value(k, p.width, p.seed)).otherwise(vec)
    return uses.select("k", "id", vec.alias("vec"), F.lit(0.0).alias("acc"), "accesses")


def train(samples: DataFrame, *, features: list[str], params: ModelParams, steps: int, label: str = "label") -> tuple[DataFrame, dict]:
    """(k, id, vec, acc, accesses) after ``steps`` steps over all samples, and the dense part.

    ``samples`` has sample_id (distinct), the label and a column of ids or id arrays per feature, none
    of them empty. A hot id is no hot task: gradients are summed per partition first, and joins on a
    skewed id are split by adaptive execution.
    """
    d, f = params.width, len(features)
    kinds = dict(samples.dtypes)
    bags = F.array(*[(F.col(x) if kinds[x].startswith("array") else F.array(x)).cast("array<bigint>") for x in features])
    long = samples.select("sample_id", F.col(label).cast("int").alias("label"), F.posexplode(bags).alias("k", "ids"))
    long = settle(long.select("sample_id", "label", "k", F.explode("ids").alias("id")))
    n = samples.count()
    tables = settle(start_tables(long, f, params))
    model = {"dense": init_dense(f, params, np.random.default_rng(params.seed)), "moments": None, "t": 0}
    shapes = [w.shape for w in model["dense"]]
    for _ in range(steps):
        dense = model["dense"]
        pooled = long.join(tables.select("k", "id", "vec"), ["k", "id"]).groupBy("sample_id", "label", "k").agg(F.array(*[F.sum(F.col("vec")[j]) for j in range(d)]).alias("e"))
        wide = pooled.groupBy("sample_id", "label").agg(F.transform(F.sort_array(F.collect_list(F.struct("k", "e"))), lambda x: x["e"]).alias("es"))

        def gradients(frames, dense=dense):
            for frame in frames:
                if not len(frame):
                    continue
                es = np.stack([np.stack(x) for x in frame["es"]])
                ge, own = backward([es[:, k] for k in range(f)], dense, frame["label"].to_numpy(), np.full(len(frame), 1.0 / n))
                flat = np.concatenate(ge, axis=1) * n
                yield pd.DataFrame({"sample_id": frame["sample_id"], "g": list(flat), "dense": None})
                yield pd.DataFrame({"sample_id": [None], "g": [None], "dense": [np.concatenate([x.reshape(-1) for x in own])]}).astype({"sample_id": "Int64"})

        made = settle(wide.mapInPandas(gradients, "sample_id bigint, g array<double>, dense array<double>"))
        per_row = (
            long.join(made.where("sample_id is not null").select("sample_id", "g"), "sample_id")
            .groupBy("k", "id")
            .agg(*[F.sum(F.get("g", F.col("k") * d + j)).alias(f"g{j}") for j in range(d)])
        )
        g = [F.col(f"g{j}") for j in range(d)]
        acc = F.col("acc") + sum((x * x for x in g[1:]), g[0] * g[0]) / d
        stepped = tables.join(per_row, ["k", "id"]).withColumn("acc", acc)
        tables = settle(
            stepped.select("k", "id", F.array(*[F.col("vec")[j] - params.table_rate * g[j] / F.sqrt(F.col("acc") + 1e-8) for j in range(d)]).alias("vec"), "acc", "accesses")
        )
        sums = made.where("sample_id is null").select(F.posexplode("dense").alias("at", "x")).groupBy("at").agg(F.sum("x").alias("x")).orderBy("at").collect()
        flat, grads, at = np.array([r["x"] for r in sums]), [], 0
        for shape in shapes:
            grads.append(flat[at : at + int(np.prod(shape))].reshape(shape))
            at += int(np.prod(shape))
        dense_step(model, grads, params)
    return tables, model
