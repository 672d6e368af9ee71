"""Global positions and next-row access without a single-partition window."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from idfold.storage import settle

#: Rows per block of a chain; a window never spans more.
BLOCK = 1 << 16


def with_positions(df: DataFrame, order: list[str], *, name: str = "pos", within: list[str] | None = None, partitions: int | None = None) -> DataFrame:
    """Number the rows from 1 in the order of ``within`` + ``order``, afresh for each value of ``within``.

    One range exchange; the offsets of ranges are a window over one row per (range, group). The
    ranged rows are written out first, as a recomputed range exchange may draw other borders.
    """
    within = within or []
    n = partitions or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    ranged = settle(df.repartitionByRange(n, *within, *order).sortWithinPartitions(*within, *order).withColumn("__part", F.spark_partition_id()))
    counts = ranged.groupBy(*within, "__part").agg(F.count("*").alias("__n"))
    before = Window.partitionBy(*within).orderBy("__part") if within else Window.orderBy("__part")
    offsets = counts.select(*within, "__part", (F.sum("__n").over(before) - F.col("__n")).alias("__before"))
    local = Window.partitionBy(*within, "__part").orderBy(*order)
    return (
        ranged.withColumn("__place", F.row_number().over(local))
        .join(F.broadcast(offsets), [*within, "__part"])
        .withColumn(name, (F.col("__before") + F.col("__place")).cast("long"))
        .drop("__part", "__place", "__before")
    )


def with_next(chain: DataFrame, keys: list[str], columns: list[str], *, pos: str = "pos", block: int = BLOCK) -> DataFrame:
    """``chain`` with next_<column> of the row at pos + 1 (null for the last of a key).

    Windows run over blocks of positions; the first row of each block is joined to the block before.
    """
    at = F.floor((F.col(pos) - 1) / block)
    blocked = chain.withColumn("__block", at)
    heads = blocked.where((F.col(pos) - 1) % block == 0).select(*keys, (F.col("__block") - 1).alias("__block"), *[F.col(c).alias(f"__head_{c}") for c in columns])
    inside = Window.partitionBy(*keys, "__block").orderBy(pos)
    led = blocked.select("*", *[F.lead(c).over(inside).alias(f"__lead_{c}") for c in columns])
    return (
        led.join(heads, [*keys, "__block"], "left")
        .select(*chain.columns, *[F.coalesce(f"__lead_{c}", f"__head_{c}").alias(f"next_{c}") for c in columns])
    )


def smallest(df: DataFrame, keys: list[str], order: list[str | Column], limit: Column, *, name: str) -> DataFrame:
    """Rank rows per ``keys`` by ``order`` and keep those up to ``limit``."""
    return df.withColumn(name, F.row_number().over(Window.partitionBy(*keys).orderBy(*order))).where(F.col(name) <= limit)
