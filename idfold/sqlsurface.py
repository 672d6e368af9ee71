"""The methods as SQL functions: ``register(spark)`` makes them callable from SQL.

Built-in expressions and joins are the fast path everywhere else; these serve ad-hoc SQL.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from idfold.operators.kernel import FoldParams, fold_arrays

#: Entries of a map that may be handed to the workers for ``fold_row``; larger maps need a join.
MAP_ENTRIES = 5_000_000


def _auc(label: pd.Series, score: pd.Series) -> float:
    from idfold.operators.student import auc

    value = auc(label.to_numpy(), score.to_numpy())
    return float("nan") if value is None else value


class _FoldChain:
    """Rows of a chain (feature, id, value, accesses) in, (feature, id, row) out, per partition of the table argument."""

    def __init__(self):
        self.rows: list[tuple] = []
        self.budget = 1

    def eval(self, row, row_budget: int):
        self.budget = row_budget
        self.rows.append((row["value"], row["id"], row["accesses"], row["feature"]))

    def terminate(self):
        rows = sorted(self.rows)
        to, _, _ = fold_arrays(np.array([r[0] for r in rows], dtype=float), np.array([r[2] for r in rows], dtype=np.int64), FoldParams(row_budget=self.budget))
        for r, k in zip(rows, to, strict=True):
            yield r[3], r[1], int(k)


def register(spark: SparkSession) -> None:
    """``vec_dot(x, y)``, ``vec_norm(x)``, ``auc(label, score)`` and ``fold_chain(TABLE(t) PARTITION BY (feature), budget)``."""
    from pyspark.sql.functions import pandas_udf, udtf

    @pandas_udf("double")
    def vec_dot(x: pd.Series, y: pd.Series) -> pd.Series:
        return pd.Series([None if a is None or b is None else float(np.dot(a, b)) for a, b in zip(x, y, strict=True)])

    @pandas_udf("double")
    def vec_norm(x: pd.Series) -> pd.Series:
        return x.map(lambda a: None if a is None else float(np.linalg.norm(a)))

    @pandas_udf("double")
    def auc(label: pd.Series, score: pd.Series) -> float:
        return _auc(label, score)

    for name, f in (("vec_dot", vec_dot), ("vec_norm", vec_norm), ("auc", auc)):
        spark.udf.register(name, f)
    spark.udtf.register("fold_chain", udtf(_FoldChain, returnType="feature string, id bigint, row bigint"))


def register_map(spark: SparkSession, fold_map: DataFrame, name: str = "fold_row") -> None:
    """``name(feature, id)``: the row of an id in slot 0, null for unknown ids. Refuses maps over MAP_ENTRIES."""
    first = fold_map.where("slot = 0").select("feature", "id", "row")
    if first.limit(MAP_ENTRIES + 1).count() > MAP_ENTRIES:
        raise ValueError("the map is too large to hand to every worker; join it instead (mapping.apply)")
    held = spark.sparkContext.broadcast({(r["feature"], r["id"]): r["row"] for r in first.collect()})  # MAP_ENTRIES at most

    @F.pandas_udf("bigint")
    def fold_row(feature: pd.Series, id_: pd.Series) -> pd.Series:
        known = held.value
        return pd.Series([known.get(k) for k in zip(feature, id_, strict=True)], dtype="Int64")

    spark.udf.register(name, fold_row)
