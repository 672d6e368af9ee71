"""Accuracy, size, collision and skew measures."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def auc(scored: DataFrame, *, keys: list[str] | None = None, label: str = "label", score: str = "score", weight: str | None = None, bins: int | None = None) -> DataFrame:
    """(keys..., positives, negatives, auc): exact, ties count half; null if a class is absent.

    Scores are first aggregated to distinct values, so the ordered pass is over those only; ``bins``
    rounds scores of 0 .. 1 to that many levels for tables whose scores are all distinct.
    """
    keys = keys or []
    w = F.col(weight) if weight else F.lit(1)
    s = F.floor(F.col(score) * bins) if bins else F.col(score)
    per = scored.groupBy(*keys, s.alias("s")).agg(
        F.sum(F.when(F.col(label) == 1, w).otherwise(0)).cast("double").alias("a"), F.sum(F.when(F.col(label) == 0, w).otherwise(0)).cast("double").alias("b")
    )
    below = F.sum("b").over(Window.partitionBy(*keys).orderBy("s").rowsBetween(Window.unboundedPreceding, -1))
    won = per.withColumn("won", F.col("a") * (F.coalesce(below, F.lit(0.0)) + F.col("b") / 2))
    total = won.groupBy(*keys).agg(F.sum("won").alias("won"), F.sum("a").alias("positives"), F.sum("b").alias("negatives"))
    area = F.when((F.col("positives") > 0) & (F.col("negatives") > 0), F.round(F.col("won") / (F.col("positives") * F.col("negatives")), 6))
    return total.select(*keys, F.col("positives").cast("long").alias("positives"), F.col("negatives").cast("long").alias("negatives"), area.alias("auc"))


def log_loss(scored: DataFrame, *, keys: list[str] | None = None, label: str = "label", score: str = "score") -> DataFrame:
    """(keys..., logloss, calibration): mean log loss and mean score over mean label."""
    p = F.least(F.greatest(F.col(score), F.lit(1e-12)), F.lit(1 - 1e-12))
    loss = -F.when(F.col(label) == 1, F.log(p)).otherwise(F.log(1 - p))
    return scored.groupBy(*(keys or [])).agg(F.round(F.avg(loss), 6).alias("logloss"), F.round(F.avg(score) / F.avg(label), 6).alias("calibration"))


def quality_delta(results: DataFrame, *, base: str) -> DataFrame:
    """(method, size, mean_auc, above_base, above_full): methods compared at equal size.

    Cells of ``results`` are named method_size, the uncompressed one ``full``.
    """
    named = results.select(F.regexp_extract("cell", "^(.*)_([0-9.]+)$", 1).alias("method"), F.regexp_extract("cell", "^(.*)_([0-9.]+)$", 2).alias("size"), "mean_auc", "cell")
    full = named.where("cell = 'full'").agg(F.max("mean_auc"))
    same = named.where(F.col("method") == base).select("size", F.col("mean_auc").alias("base"))
    return named.where("method != ''").join(same, "size", "left").select(
        "method", "size", "mean_auc", F.round(F.col("mean_auc") - F.col("base"), 6).alias("above_base"), F.round(F.col("mean_auc") - full.scalar(), 6).alias("above_full")
    )


def mean_reps(results: DataFrame, *, keys: list[str]) -> DataFrame:
    """Mean, least and greatest AUC over repetitions, and their number."""
    return results.groupBy(*keys).agg(F.round(F.avg("auc"), 6).alias("mean_auc"), F.min("auc").alias("min_auc"), F.max("auc").alias("max_auc"), F.count("auc").alias("reps"))


def row_loads(fold_map: DataFrame, counts: DataFrame) -> DataFrame:
    """(feature, slot, row, z, c, c2): ids, uses and summed squared uses of every row."""
    return fold_map.join(counts.select("feature", "id", "accesses"), ["feature", "id"]).groupBy("feature", "slot", "row").agg(
        F.count("*").alias("z"), F.sum("accesses").alias("c"), F.sum(F.col("accesses") * F.col("accesses")).alias("c2")
    )


def collisions(fold_map: DataFrame, counts: DataFrame) -> DataFrame:
    """Per feature and slot: ids, rows used, colliding id pairs, colliding pairs of uses."""
    return row_loads(fold_map, counts).groupBy("feature", "slot").agg(
        F.sum("z").alias("ids"), F.count("*").alias("rows_used"), (F.sum("z") - F.count("*")).alias("collisions"),
        F.sum(F.expr("z * (z - 1) div 2")).alias("id_pairs"), F.sum(F.expr("(c * c - c2) div 2")).alias("use_pairs"),
    )


def load_report(fold_map: DataFrame, counts: DataFrame, *, cap: int) -> DataFrame:
    """Per feature and slot: greatest and 99th percentile row load, share of rows at the cap."""
    return row_loads(fold_map, counts).groupBy("feature", "slot").agg(
        F.max("z").alias("max_load"), F.percentile("z", 0.99).alias("p99_load"), F.round(F.avg(F.when(F.col("z") >= cap, 1.0).otherwise(0.0)), 6).alias("at_cap")
    )


def purity(fold_map: DataFrame, class_uses: DataFrame) -> DataFrame:
    """Per feature and slot: uses that agree with the dominant class of their row, over all uses.

    ``class_uses``: feature, id, class, n. Evaluate on uses that the map was not learned from.
    """
    per = fold_map.join(class_uses, ["feature", "id"]).groupBy("feature", "slot", "row", "class").agg(F.sum("n").alias("n"))
    rows = per.groupBy("feature", "slot", "row").agg(F.max("n").alias("top"), F.sum("n").alias("all"))
    return rows.groupBy("feature", "slot").agg(F.sum("all").alias("uses"), F.round(F.sum("top") / F.sum("all"), 6).alias("purity"))


def within_row_variance(fold_map: DataFrame, teacher: DataFrame) -> DataFrame:
    """Use-weighted variance of the latent value inside rows. ``teacher``: feature, id, value, accesses."""
    j = fold_map.join(teacher.select("feature", "id", "value", "accesses"), ["feature", "id"])
    rows = j.groupBy("feature", "slot", "row").agg(
        F.sum("accesses").alias("c"), F.sum(F.col("accesses") * F.col("value")).alias("s"), F.sum(F.col("accesses") * F.col("value") * F.col("value")).alias("q")
    ).where("c > 0")
    return rows.groupBy("feature", "slot").agg(F.round(F.sum(F.col("q") - F.col("s") * F.col("s") / F.col("c")) / F.sum("c"), 3).alias("variance"))


def skew(counts: DataFrame, *, top: int = 100) -> DataFrame:
    """Per feature: ids, uses, ids used once, share of the ``top`` ids, Gini coefficient of the uses.

    Ids are aggregated to distinct counts first, which bounds the ordered passes.
    """
    per = counts.groupBy("feature", F.col("accesses").alias("c")).agg(F.count("*").alias("k"))
    up = Window.partitionBy("feature").orderBy("c").rowsBetween(Window.unboundedPreceding, -1)
    down = Window.partitionBy("feature").orderBy(F.desc("c")).rowsBetween(Window.unboundedPreceding, -1)
    ranked = per.withColumn("before", F.coalesce(F.sum("k").over(up), F.lit(0))).withColumn("above", F.coalesce(F.sum("k").over(down), F.lit(0)))
    in_top = F.greatest(F.least(F.lit(top) - F.col("above"), F.col("k")), F.lit(0))
    # Sum over ids of rank * count, ranks from 1 in ascending order.
    rank_sum = F.col("k") * F.col("before") + F.expr("k * (k + 1) div 2")
    agg = ranked.groupBy("feature").agg(
        F.sum("k").alias("ids"), F.sum(F.col("c") * F.col("k")).alias("uses"), F.sum(F.when(F.col("c") == 1, F.col("k")).otherwise(0)).alias("once"),
        F.sum(F.col("c") * in_top).alias("top_uses"), F.sum(rank_sum * F.col("c")).alias("ranked"),
    )
    gini = 2.0 * F.col("ranked") / (F.col("ids") * F.col("uses")) - (F.col("ids") + 1.0) / F.col("ids")
    return agg.select("feature", "ids", "uses", "once", F.round(F.col("top_uses") / F.col("uses"), 6).alias("top_share"), F.round(gini, 6).alias("gini"))


def heights_summary(heights: DataFrame) -> DataFrame:
    """Number of tables, greatest and median height, quartiles."""
    q = F.percentile("height", F.array(F.lit(0.25), F.lit(0.5), F.lit(0.75)))
    one = heights.agg(F.count("*").alias("tables"), F.max("height").alias("max_height"), q.alias("q"))
    return one.select("tables", "max_height", F.col("q")[0].alias("p25"), F.col("q")[1].alias("median"), F.col("q")[2].alias("p75"))
