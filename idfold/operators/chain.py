"""Chains as DataFrames: building, links, gates, runs, merging, and the two folding engines.

The local engine hands each (feature, dim) chain to one task (about 100 bytes an id there, so some ten
million ids in an executor of a few GB). The distributed engine keeps a single chain spread over
blocks of positions and does each round as DataFrame operations; see ``step``.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from idfold import schemas
from idfold.operators.kernel import FoldParams, fold_arrays
from idfold.plans.ordering import with_next, with_positions
from idfold.storage import settle

KEYS = ["feature", "dim"]


def build(teacher: DataFrame, *, dims: int | None = None) -> DataFrame:
    """Chain of singletons per latent dimension: positions from 1 in the order (value, id).

    One range exchange in total; later rounds never sort values again.
    """
    vec = F.slice("vec", 1, dims) if dims else F.col("vec")
    long = teacher.select("feature", "id", "accesses", F.posexplode(vec).alias("dim", "value"))
    return with_positions(long, ["value", "id"], within=KEYS).withColumn("size", F.lit(1).cast("long"))


def links(chain: DataFrame) -> DataFrame:
    """One link per pair of neighbours with its three scores; link i joins positions i and i + 1."""
    norms = chain.groupBy(*KEYS).agg(F.sqrt(F.sum(F.col("accesses").cast("double") * F.col("accesses").cast("double"))).alias("norm"))
    q = lambda c: F.when(F.col("norm") > 0, 1 + F.col(c) / F.col("norm")).otherwise(F.lit(1.0))
    return (
        with_next(chain, KEYS, ["value", "size", "accesses"])
        .where("next_value is not null")
        .join(F.broadcast(norms), KEYS)
        .select(
            *KEYS, "pos", (q("accesses") * q("next_accesses")).alias("rarity"), (F.col("next_value") - F.col("value")).alias("gap"),
            (F.col("size") + F.col("next_size")).alias("bulk"),
        )
    )


def merges_to_do(chain: DataFrame, params: FoldParams) -> DataFrame:
    """(feature, dim, n, r): clusters and merges of the coming round; chains that are done are left out."""
    n = chain.groupBy(*KEYS).agg(F.count("*").alias("n"))
    return n.withColumn("r", F.least(F.lit(params.stride), F.col("n") - params.row_budget)).where("r > 0")


#: Fractions at which quantiles of a score are taken, each a quarter over the one before.
_FRACTIONS = [min(1.0, 0.0005 * 1.25**k) for k in range(36)]
_ACCURACY = 20_000


def leading(df: DataFrame, score: str, tie: str, width: Column) -> DataFrame:
    """Rows of each chain that come first in the order (score, tie): at least ``width`` of them, and not many more.

    Two aggregates per chain find a score that at least ``width`` rows reach, and among the rows
    of just that score a tie-breaker; no window ever sees the rest of a chain.
    """
    fractions = F.array(*[F.lit(x) for x in _FRACTIONS])
    n = df.groupBy(*KEYS).agg(F.count("*").alias("n_links"), F.max(width).alias("width"), F.percentile_approx(score, fractions, _ACCURACY).alias("q"))
    # The sketch errs by a 1 / _ACCURACY share of the rows at most; twice that is added.
    reach = F.col("width") / F.col("n_links") + 2.0 / _ACCURACY
    at = F.filter(F.arrays_zip(fractions.alias("f"), F.col("q").alias("v")), lambda e: e["f"] >= reach)
    bound = n.select(*KEYS, "width", F.coalesce(F.get(at, F.lit(0))["v"], F.element_at("q", -1)).alias("bound"))
    near = df.join(F.broadcast(bound), KEYS)
    ties = near.groupBy(*KEYS).agg(
        F.sum(F.when(F.col(score) < F.col("bound"), 1).otherwise(0)).alias("below"), F.sum(F.when(F.col(score) == F.col("bound"), 1).otherwise(0)).alias("equal"),
        F.max("width").alias("w"), F.percentile_approx(F.when(F.col(score) == F.col("bound"), F.col(tie)), fractions, _ACCURACY).alias("tq"),
    )
    need = (F.col("w") - F.col("below")) / F.greatest(F.col("equal"), F.lit(1)) + 2.0 / _ACCURACY
    place = F.filter(F.arrays_zip(fractions.alias("f"), F.col("tq").alias("v")), lambda e: e["f"] >= need)
    last = F.when(need <= 1, F.get(place, F.lit(0))["v"])
    limits = ties.select(*KEYS, last.alias("last"))
    kept = near.join(F.broadcast(limits), KEYS).where((F.col(score) < F.col("bound")) | ((F.col(score) == F.col("bound")) & (F.col("last").isNull() | (F.col(tie) <= F.col("last")))))
    return kept.select(*df.columns)


def _ranked(df: DataFrame, rank: str, order: list[Column], width: Column | None) -> DataFrame:
    out = df.withColumn(rank, F.row_number().over(Window.partitionBy(*KEYS).orderBy(*order)))
    return out if width is None else out.where(F.col(rank) <= width)


def gate(scored: DataFrame, params: FoldParams) -> DataFrame:
    """The links that pass all gates, with the rank at each place and the fallback flag.

    ``scored`` holds links with a column r. Every place ranks by (its score, the rank before,
    position) per chain and keeps the first of its width. The first place, which alone sees all
    links, cuts them down by quantiles before it ranks.
    """
    now, order = scored.withColumn("fallback", F.lit(False)), "pos"
    if not params.gates:
        return _ranked(leading(now, "pos", "pos", F.col("r")), "rank1", [F.col("pos")], F.col("r"))
    for place, name in enumerate(params.gates):
        last = place == len(params.gates) - 1
        multiple = params.widths[-len(params.gates) :][place]
        width = F.greatest(F.lit(1), F.floor(F.lit(multiple) * F.col("r")))
        rank = f"rank{place + 1}"
        if name == "bulk":
            fits = F.col("bulk") < params.size_cap if params.strict else F.col("bulk") <= params.size_cap
            some = now.groupBy(*KEYS).agg(F.max(fits).alias("some_fit"))
            flagged = now.drop("fallback").join(F.broadcast(some), KEYS).withColumn("fallback", ~F.col("some_fit")).drop("some_fit")
            good, rest = flagged.where(~F.col("fallback") & fits), flagged.where("fallback")
            limit = width if last and params.bulk_limit == "stride" else None
            if place == 0:
                good = leading(good, order, order, width) if limit is not None else good
                rest = leading(rest, "bulk", order, width)
            # Without a limit the order before serves as rank; no window over all that fits.
            good = _ranked(good, rank, [F.col(order)], limit) if limit is not None or place else good.withColumn(rank, F.col(order))
            now = good.unionByName(_ranked(rest, rank, [F.col("bulk"), F.col(order)], width))
        else:
            now = leading(now, name, order, width) if place == 0 else now
            now = _ranked(now, rank, [F.col(name), F.col(order)], width)
        order = rank
    return now


def runs(selected: DataFrame, chain: DataFrame) -> DataFrame:
    """Selected links with run_id, their rank in the run and the run's merged size (gaps and islands)."""
    by_pos = Window.partitionBy(*KEYS).orderBy("pos")
    island = selected.withColumn("run_id", F.col("pos") - F.row_number().over(by_pos))
    sizes = chain.select(*KEYS, F.col("pos"), "size", F.col("size").alias("own"))
    nexts = with_next(sizes, KEYS, ["size"]).select(*KEYS, "pos", "own", "next_size")
    run = Window.partitionBy(*KEYS, "run_id")
    return (
        island.join(nexts, [*KEYS, "pos"])
        .withColumn("in_run", F.row_number().over(run.orderBy("pos")))
        .withColumn("run_size", F.sum("next_size").over(run) + F.min(F.when(F.col("in_run") == 1, F.col("own"))).over(run))
    )


def split_runs(run_links: DataFrame, params: FoldParams) -> DataFrame:
    """Links that stay: all of runs within the cap or after a fallback; of the rest every other one, or those of a greedy packing."""
    if "bulk" not in params.gates:
        return run_links
    fits = lambda size: size < params.size_cap if params.strict else size <= params.size_cap
    whole = fits(F.col("run_size")) | F.col("fallback")
    if params.split == "pairs":
        return run_links.where(whole | (F.col("in_run") % 2 == 1))
    if params.split != "pack":
        raise ValueError(f"unknown split {params.split!r}")
    start = F.struct(F.lit(0).cast("long").alias("held"), F.array().cast("array<bigint>").alias("stay"))

    def step(acc: Column, link: Column) -> Column:
        held = F.when(link["in_run"] == 1, link["own"]).otherwise(acc["held"])
        grown = held + link["next_size"]
        joins = fits(grown)
        return F.struct(F.when(joins, grown).otherwise(link["next_size"]).alias("held"), F.when(joins, F.concat(acc["stay"], F.array(link["pos"]))).otherwise(acc["stay"]).alias("stay"))

    # One row per run over the cap: its links in order, packed from the left. A run that packs nothing keeps its first link.
    over = run_links.where(~whole).groupBy(*KEYS, "run_id").agg(F.sort_array(F.collect_list(F.struct("in_run", "pos", "own", "next_size"))).alias("links"))
    packed = over.select(*KEYS, F.aggregate("links", start, step, lambda acc: acc["stay"]).alias("stay"), F.col("links")[0]["pos"].alias("first"))
    kept = packed.select(*KEYS, F.explode(F.when(F.size("stay") > 0, F.col("stay")).otherwise(F.array("first"))).alias("pos"))
    return run_links.where(whole).select(*KEYS, "pos").unionByName(kept)


def merge(chain: DataFrame, stay: DataFrame, params: FoldParams, *, block: int = 1 << 16) -> DataFrame:
    """The shorter chain: new position = position less the merged links before it."""
    marked = chain.join(stay.select(*KEYS, (F.col("pos") + 1).alias("pos"), F.lit(1).alias("joined")), [*KEYS, "pos"], "left").withColumn(
        "joined", F.coalesce("joined", F.lit(0))
    )
    marked = marked.withColumn("block", F.floor((F.col("pos") - 1) / block))
    per_block = marked.groupBy(*KEYS, "block").agg(F.sum("joined").alias("in_block"))
    before = per_block.select(*KEYS, "block", (F.sum("in_block").over(Window.partitionBy(*KEYS).orderBy("block")) - F.col("in_block")).alias("before"))
    inside = Window.partitionBy(*KEYS, "block").orderBy("pos").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    numbered = (
        marked.withColumn("here", F.sum("joined").over(inside))
        .join(F.broadcast(before), [*KEYS, "block"])
        .withColumn("new_pos", F.col("pos") - F.col("before") - F.col("here"))
    )
    m = F.count("*")
    weight = {"mean": None, "count_weighted": "accesses", "size_weighted": "size"}[params.value_rule]
    if params.micro:
        plain = F.expr("(2 * sum(value) + count(*)) div (2 * count(*))")
        value = plain if weight is None else F.expr(f"CASE WHEN sum({weight}) > 0 THEN (2 * sum(value * {weight}) + sum({weight})) div (2 * sum({weight})) ELSE (2 * sum(value) + count(*)) div (2 * count(*)) END")
    else:
        plain = F.sum("value") / m
        value = plain if weight is None else F.when(F.sum(weight) > 0, F.sum(F.col("value") * F.col(weight)) / F.sum(weight)).otherwise(plain)
    # Rounding must not carry a mean out of its members, which would break the order.
    value = F.greatest(F.least(value, F.max("value")), F.min("value"))
    return numbered.groupBy(*KEYS, F.col("new_pos").alias("pos")).agg(value.alias("value"), F.sum("size").alias("size"), F.sum("accesses").alias("accesses"))


def step(chain: DataFrame, params: FoldParams) -> tuple[DataFrame, DataFrame]:
    """One distributed round: the next chain, and (feature, dim, pos) of the links merged.

    Chains that already meet the budget pass through. ``params`` must have stride and cap.
    """
    todo = merges_to_do(chain, params)
    scored = links(chain).join(F.broadcast(todo), KEYS)
    stay = split_runs(runs(gate(scored, params), chain), params)
    return merge(chain, stay, params), stay


def fold_distributed(chain: DataFrame, params: FoldParams) -> tuple[DataFrame, DataFrame]:
    """Rounds until every chain meets the budget: final clusters and their position intervals (cuts).

    Stride and cap that are left out follow from the length of each chain, as in the local engine;
    chains of different lengths are then folded one after the other. Each round is written to the
    shared folder; the driver sees one number per chain and round. A round that merges nothing raises.
    """
    start = settle(chain.select(*KEYS, "pos", "value", "size", "accesses"))
    lengths = {tuple(r[k] for k in KEYS): r["n"] for r in start.groupBy(*KEYS).agg(F.count("*").alias("n")).collect()}
    alike = params.stride is not None and params.size_cap is not None
    groups = [None] if alike else sorted(set(lengths.values()))
    done = []
    for n in groups:
        own = params.resolved(n or 0)
        names = [k for k, size in lengths.items() if n is None or size == n]
        at = F.lit(False)
        for feature, dim in names:
            at = at | ((F.col("feature") == feature) & (F.col("dim") == dim))
        now, rounds, left = start if n is None else start.where(at), 0, sum(lengths[k] for k in names)
        while not merges_to_do(now, own).isEmpty() and (own.max_rounds is None or rounds < own.max_rounds):
            now = settle(step(now, own)[0])
            rounds, before, left = rounds + 1, left, now.count()
            if left >= before:
                raise RuntimeError(f"round {rounds} merged nothing")
        done.append(now)
    clusters = done[0] if done else start
    for more in done[1:]:
        clusters = clusters.unionByName(more)
    return clusters, cuts_of(clusters)


def cuts_of(clusters: DataFrame, *, block: int = 1 << 16) -> DataFrame:
    """Position intervals of clusters: running sums of sizes, block by block."""
    blocked = clusters.withColumn("block", F.floor((F.col("pos") - 1) / block))
    per_block = blocked.groupBy(*KEYS, "block").agg(F.sum("size").alias("in_block"))
    before = per_block.select(*KEYS, "block", (F.sum("in_block").over(Window.partitionBy(*KEYS).orderBy("block")) - F.col("in_block")).alias("before"))
    inside = Window.partitionBy(*KEYS, "block").orderBy("pos").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return (
        blocked.withColumn("upto", F.sum("size").over(inside))
        .join(F.broadcast(before), [*KEYS, "block"])
        .select(
            "feature", "dim", (F.col("pos") - 1).alias("row"), (F.col("before") + F.col("upto") - F.col("size") + 1).alias("lo_pos"),
            (F.col("before") + F.col("upto")).alias("hi_pos"), F.col("value").cast("double").alias("value"), "size", "accesses",
        )
    )


def _ordered(group: pd.DataFrame) -> pd.DataFrame:
    return group.sort_values("pos", kind="stable")


def fold_local(chain: DataFrame, params: FoldParams) -> DataFrame:
    """Cuts of every chain; one task per (feature, dim), all rounds inside it."""

    def run(group: pd.DataFrame) -> pd.DataFrame:
        g = _ordered(group)
        row, clusters, _ = fold_arrays(g["value"].to_numpy(), g["accesses"].to_numpy(), params)
        n = len(clusters)
        lo = np.searchsorted(row, np.arange(n)) + 1
        return pd.DataFrame(
            {"feature": g["feature"].iloc[0], "dim": g["dim"].iloc[0], "row": np.arange(n), "lo_pos": lo, "hi_pos": lo + clusters.size - 1, "value": clusters.value.astype(float), "size": clusters.size, "accesses": clusters.count}
        )

    return chain.groupBy(*KEYS).applyInPandas(run, schemas.CUTS)


def fold_trace(chain: DataFrame, params: FoldParams) -> DataFrame:
    """What every round of the local engine did."""

    def run(group: pd.DataFrame) -> pd.DataFrame:
        g = _ordered(group)
        _, _, trace = fold_arrays(g["value"].to_numpy(), g["accesses"].to_numpy(), params)
        out = pd.DataFrame(trace, columns=["round", "n", "r", "links", "kept1", "kept2", "fallback", "selected", "runs_split", "merges"])
        return out.assign(feature=g["feature"].iloc[0], dim=g["dim"].iloc[0])[["feature", "dim", *out.columns]]

    return chain.groupBy(*KEYS).applyInPandas(run, schemas.TRACE)


def fold(chain: DataFrame, params: FoldParams, *, engine: str = "local") -> DataFrame:
    """Cuts by either engine."""
    if engine == "local":
        return fold_local(chain, params)
    if engine != "distributed":
        raise ValueError(f"unknown engine {engine!r}")
    return fold_distributed(chain, params)[1]
