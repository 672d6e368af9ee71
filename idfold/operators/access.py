"""Access counting over samples, batch form (the streaming form is in idfold.streaming)."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def long_ids(samples: DataFrame, features: list[str]) -> DataFrame:
    """(sample_id, feature, id) from wide samples; array columns are bags."""
    kinds = dict(samples.dtypes)

    def entries(feature: str):
        bag = F.col(feature) if kinds[feature].startswith("array") else F.array(feature)
        return F.transform(bag, lambda x: F.struct(F.lit(feature).alias("feature"), x.cast("long").alias("id")))

    parts = [entries(f) for f in features]
    return samples.select("sample_id", F.explode(F.concat(*parts)).alias("e")).select("sample_id", "e.feature", "e.id").where("id is not null")


def count(samples: DataFrame, *, features: list[str], vocab: DataFrame | None = None) -> DataFrame:
    """(feature, id, accesses): uses of every id; ids of ``vocab(feature, id)`` without a use get 0.

    Partial sums are made before the exchange, so what travels grows with distinct ids only.
    """
    counts = long_ids(samples, features).groupBy("feature", "id").agg(F.count("*").alias("accesses"))
    if vocab is None:
        return counts
    return vocab.select("feature", "id").join(counts, ["feature", "id"], "left").select("feature", "id", F.coalesce("accesses", F.lit(0)).cast("long").alias("accesses"))
