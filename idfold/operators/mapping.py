"""Fold maps: emission, budgets, lookups through them, saving, relevance."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from idfold.functions.hashing import universal
from idfold.functions.vectors import bits_needed

#: Maps up to this many bytes (16 per entry) are broadcast to lookups; larger ones are shuffled.
BROADCAST_BYTES = 200 << 20


def emit(chain: DataFrame, cuts: DataFrame) -> DataFrame:
    """Id -> row, with the latent dimension as slot: every cut names its positions, then an equi-join."""
    spans = cuts.select("feature", "dim", "row", F.explode(F.sequence("lo_pos", "hi_pos")).alias("pos"))
    return chain.select("feature", "dim", "pos", "id").join(spans, ["feature", "dim", "pos"]).select("feature", F.col("dim").alias("slot"), "id", "row")


def emit_range_join(chain: DataFrame, cuts: DataFrame) -> DataFrame:
    """The same as an interval join, for few cuts (they are broadcast)."""
    c = cuts.select(F.col("feature").alias("f"), F.col("dim").alias("d"), "row", "lo_pos", "hi_pos")
    on = (F.col("feature") == F.col("f")) & (F.col("dim") == F.col("d")) & F.col("pos").between(F.col("lo_pos"), F.col("hi_pos"))
    return chain.join(F.broadcast(c), on).select("feature", F.col("dim").alias("slot"), "id", "row")


def plan(heights: DataFrame, *, size_pct: float, skip_below: int = 100_000, slots: int = 1, budget_mode: str = "split") -> DataFrame:
    """(feature, height, folded, rows_per_slot, total_rows): rows for every table at a size target.

    Tables under ``skip_below`` rows stay whole. ``split`` shares the rows of a table among its
    slots, ``each`` gives every slot all of them.
    """
    folded = F.col("height") >= skip_below
    target = F.greatest(F.ceil(F.col("height") * size_pct / 100.0), F.lit(1))
    per_slot = F.greatest(F.floor(target / slots), F.lit(1)) if budget_mode == "split" else target
    rows = F.when(folded, per_slot).otherwise(F.col("height")).cast("long")
    return heights.select("feature", "height", folded.alias("folded"), rows.alias("rows_per_slot"), F.when(folded, rows * slots).otherwise(rows).cast("long").alias("total_rows"))


def size_report(planned: DataFrame, *, width: int = 16, bits: int = 32, full_width: int = 16) -> DataFrame:
    """One row: parameters and bits of the folded tables against the original ones."""
    return planned.agg(
        F.sum(F.col("height") * full_width).alias("full_params"),
        F.sum(F.col("total_rows") * width).alias("folded_params"),
        F.round(100.0 * F.sum(F.col("total_rows") * width * bits) / F.sum(F.col("height") * full_width * 32), 6).alias("size_pct"),
    )


def map_memory(fold_map: DataFrame) -> DataFrame:
    """Entries of the lookups, rows of the tallest table, bits per entry and bytes in all."""
    tall = fold_map.agg(F.count("*").alias("entries"), (F.max("row") + 1).alias("tallest"))
    return tall.select("entries", "tallest", bits_needed(F.col("tallest")).alias("bits"), F.ceil(F.col("entries") * bits_needed(F.col("tallest")) / 8.0).cast("long").alias("bytes"))


def apply(ids: DataFrame, fold_map: DataFrame, *, height: int | None = None, how: str = "auto") -> DataFrame:
    """Rows of ids through a map: ``ids(feature, id, ...)`` gains slot and row.

    Ids outside 0 .. height - 1 are hashed into the range first. ``auto`` broadcasts the map if its
    size is under BROADCAST_BYTES; broadcast, merge and shuffle_hash force a strategy.
    """
    if height is not None:
        inside = (F.col("id") >= 0) & (F.col("id") < height)
        ids = ids.withColumn("id", F.when(inside, F.col("id")).otherwise(universal(F.abs("id"), height)))
    if how == "auto":
        bound = BROADCAST_BYTES // 16
        how = "broadcast" if fold_map.limit(bound + 1).count() <= bound else "shuffle_hash"
    return ids.join(fold_map.hint(how), ["feature", "id"])


def apply_salted(ids: DataFrame, fold_map: DataFrame, *, hot: DataFrame, salts: int = 8) -> DataFrame:
    """Shuffled lookup with hot ids spread over ``salts`` copies of their map entries."""
    marked = ids.join(F.broadcast(hot.select("feature", "id").withColumn("hot", F.lit(True))), ["feature", "id"], "left")
    salted = marked.withColumn("salt", F.when(F.col("hot"), F.pmod(F.xxhash64(*ids.columns), F.lit(salts))).otherwise(F.lit(0)))
    copies = fold_map.join(F.broadcast(hot.select("feature", "id").withColumn("hot", F.lit(True))), ["feature", "id"], "left").withColumn(
        "salt", F.explode(F.when(F.col("hot"), F.sequence(F.lit(0), F.lit(salts - 1))).otherwise(F.array(F.lit(0))))
    )
    return salted.drop("hot").hint("merge").join(copies.drop("hot").withColumn("salt", F.col("salt").cast("long")), ["feature", "id", "salt"]).drop("salt")


def lookup(samples: DataFrame, fold_map: DataFrame, tables: DataFrame, *, slots: int, combine: str = "sum") -> DataFrame:
    """One vector per (sample, feature): ids (sample_id, feature, id) through map and internal tables.

    Bags are summed per slot; slots are summed or concatenated. Vectors stay arrays: one aggregate,
    summed on the map side first, brings the rows of a sample and feature together.
    """
    rows = apply(samples, fold_map)
    vec = rows.join(tables.select("feature", "slot", "row", "vec"), ["feature", "slot", "row"])
    add = lambda acc, x: F.zip_with(acc, x, lambda a, b: F.coalesce(a, F.lit(0.0)) + F.coalesce(b, F.lit(0.0)))
    none = F.array().cast("array<double>")
    sums = [F.aggregate(F.collect_list(F.when(F.col("slot") == s, F.col("vec"))), none, add).alias(f"s{s}") for s in range(slots)]
    per = vec.withColumn("vec", F.col("vec").cast("array<double>")).groupBy("sample_id", "feature").agg(*sums)
    parts = [F.col(f"s{s}") for s in range(slots)]
    whole = F.concat(*parts) if combine == "concat" else F.aggregate(F.array(*parts), none, add)
    return per.select("sample_id", "feature", whole.alias("vec"))


def expand_gradients(grads: DataFrame, fold_map: DataFrame, *, slots: int, width: int, combine: str = "sum") -> DataFrame:
    """(feature, slot, row, grad): gradients (feature, id, grad) of looked-up vectors spread over the internal tables.

    Summed tables take the whole gradient in every slot, concatenated ones their slice of ``width`` /
    ``slots`` entries. Rows are summed on the map side before the exchange, so a hot row is no hot task.
    """
    part = width if combine == "sum" else width // slots
    found = apply(grads, fold_map)
    place = F.lit(0) if combine == "sum" else F.col("slot") * part
    sums = found.groupBy("feature", "slot", "row").agg(*[F.sum(F.get("grad", place + j)).alias(f"g{j}") for j in range(part)])
    return sums.select("feature", "slot", "row", F.array(*[F.col(f"g{j}") for j in range(part)]).alias("grad"))


def retain(counts: DataFrame, folded: DataFrame, *, kept: DataFrame) -> DataFrame:
    """Private rows for the ids of ``kept(feature, id, row)``, then ``folded`` shifted behind them."""
    sizes = kept.groupBy("feature").agg((F.max("row") + 1).alias("shift"))
    rest = folded.join(kept.select("feature", "id"), ["feature", "id"], "left_anti").join(F.broadcast(sizes), "feature", "left")
    return kept.select("feature", F.lit(0).alias("slot"), "id", "row").unionByName(
        rest.select("feature", "slot", "id", (F.col("row") + F.coalesce("shift", F.lit(0))).alias("row"))
    )


def save(fold_map: DataFrame, path: str, *, version: str) -> None:
    """Parquet by version, feature and slot; rows sorted by id so that entries pack tightly."""
    fold_map.withColumn("version", F.lit(version)).sortWithinPartitions("feature", "slot", "id").write.mode("append").partitionBy("version", "feature", "slot").parquet(path)


def load(spark: SparkSession, path: str, *, version: str) -> DataFrame:
    df = spark.read.parquet(path).where(F.col("version") == version)
    return df.select("feature", F.col("slot").cast("int").alias("slot"), "id", "row")


def relevance(fold_map: DataFrame, new_counts: DataFrame) -> DataFrame:
    """Per feature: uses in new data, uses of ids the map knows, and the share of unseen uses."""
    known = fold_map.select("feature", "id").distinct().withColumn("known", F.lit(1))
    joined = new_counts.join(known, ["feature", "id"], "left")
    return joined.groupBy("feature").agg(
        F.sum("accesses").alias("uses"), F.sum(F.when(F.col("known") == 1, F.col("accesses")).otherwise(0)).alias("known_uses")
    ).withColumn("unseen_share", F.round(1 - F.col("known_uses") / F.col("uses"), 6))
