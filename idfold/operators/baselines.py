"""Baselines and rejected alternatives: maps that know less than a learned one.

Each takes a vocabulary or counts with columns feature, id (and accesses) and returns a fold map.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from idfold.functions.hashing import universal


def _map(df: DataFrame, row, slot: int = 0) -> DataFrame:
    return df.select("feature", F.lit(slot).alias("slot"), "id", row.cast("long").alias("row"))


def identity(vocab: DataFrame) -> DataFrame:
    return _map(vocab, F.col("id"))


def modulo(vocab: DataFrame, rows: int) -> DataFrame:
    return _map(vocab, F.pmod("id", F.lit(rows)))


def hashed(vocab: DataFrame, rows: int, *, seed: int = 0, slots: int = 1) -> DataFrame:
    """Random hash; several slots use independent hashes."""
    out = _map(vocab, universal(F.col("id"), rows, seed))
    for s in range(1, slots):
        out = out.unionByName(_map(vocab, universal(F.col("id"), rows, seed + s), s))
    return out


def quotient_remainder(vocab: DataFrame, rows: int) -> DataFrame:
    """Two complementary slots: remainder and quotient, so that no two ids share both rows."""
    return _map(vocab, F.pmod("id", F.lit(rows))).unionByName(_map(vocab, F.floor(F.col("id") / rows), 1))


def by_frequency(counts: DataFrame) -> DataFrame:
    """counts with nth, the rank by (accesses descending, id) per feature, from 1."""
    return counts.withColumn("nth", F.row_number().over(Window.partitionBy("feature").orderBy(F.desc("accesses"), "id")))


def kept_rows(counts: DataFrame, pct: float) -> DataFrame:
    """(feature, id, row): the most used ``pct`` percent of ids, rows in order of use."""
    n = F.count("*").over(Window.partitionBy("feature"))
    return by_frequency(counts).withColumn("n", n).where(F.col("nth") <= F.ceil(F.col("n") * pct / 100.0)).select("feature", "id", (F.col("nth") - 1).cast("long").alias("row"))


def retain_double_hash(counts: DataFrame, rows: int, pct: float, *, second: int | None = None) -> DataFrame:
    """The most used ids get private rows of slot 0; the others two hashed rows, one per slot.

    ``rows`` is the height of the first internal table, private rows first, ``second`` that of the
    second (the same unless given).
    """
    ranked = by_frequency(counts).withColumn("n", F.count("*").over(Window.partitionBy("feature"))).withColumn("kept", F.ceil(F.col("n") * pct / 100.0))
    room = F.lit(rows) - F.col("kept")
    slot0 = F.when(F.col("nth") <= F.col("kept"), F.col("nth") - 1).otherwise(F.col("kept") + universal(F.col("id"), room, 0))
    return _map(ranked, slot0).unionByName(_map(ranked.where("nth > kept"), universal(F.col("id"), F.lit(second or rows), 1), 1))


def truncate(counts: DataFrame, rows: int) -> DataFrame:
    """The ``rows`` - 1 most used ids keep rows; all others share the last one."""
    return _map(by_frequency(counts), F.least(F.col("nth"), F.lit(rows)) - 1)


def attribute(vocab: DataFrame, attr: str) -> DataFrame:
    """Ids of equal attribute share a row."""
    return _map(vocab, F.dense_rank().over(Window.partitionBy("feature").orderBy(attr)) - 1)


def quantile(teacher: DataFrame, rows: int) -> DataFrame:
    """Equal-size groups along the latent value."""
    return _map(teacher, F.ntile(rows).over(Window.partitionBy("feature").orderBy("value", "id")) - 1)


def quantile_access(teacher: DataFrame, rows: int) -> DataFrame:
    """Groups of about equal use along the latent value."""
    by = Window.partitionBy("feature").orderBy("value", "id")
    before = F.sum("accesses").over(by) - F.col("accesses")
    total = F.greatest(F.sum("accesses").over(Window.partitionBy("feature")), F.lit(1))
    return _map(teacher, F.least(F.floor(before * rows / total), F.lit(rows - 1)))


def cooccurrence(uses: DataFrame, *, min_support: int = 3) -> DataFrame:
    """(a, b, together, pmi): ids used in one sample, a < b; all samples count, whatever their size.

    Work grows with the square of the bag: the combinatorial cost for which this alternative was
    rejected. Ids in fewer than ``min_support`` samples form no pairs, as none of theirs can reach it.
    """
    every = uses.select("sample_id", "id").distinct()
    singles = every.groupBy("id").agg(F.count("*").alias("n"))
    bags = every.join(singles.where(F.col("n") >= min_support).select("id"), "id", "left_semi")
    total = every.agg(F.count_distinct("sample_id").alias("s"))
    x, y = bags.select("sample_id", F.col("id").alias("a")), bags.select("sample_id", F.col("id").alias("b"))
    pairs = x.join(y, "sample_id").where("a < b").groupBy("a", "b").agg(F.count("*").alias("together")).where(F.col("together") >= min_support)
    return (
        pairs.join(singles.select(F.col("id").alias("a"), F.col("n").alias("na")), "a")
        .join(singles.select(F.col("id").alias("b"), F.col("n").alias("nb")), "b")
        .select("a", "b", "together", F.round(F.log(F.col("together") * total.scalar() / (F.col("na") * F.col("nb"))), 6).alias("pmi"))
    )
