"""The experiments as queries: grids of student models over folded words, and dataset tables.

Sample set: single words of documents without the 100 most used ones, label French, day = doc_id
mod 8 + 1; the teacher sees days 1-7, the student trains on day 5, day 8 is for evaluation. The second
set are order lines with a planted label. Every cell reports the mean AUC over repetitions and its
spread, what it is above the uncompressed model, the rows used and the data it trained on.
"""

from __future__ import annotations

import math
from dataclasses import replace
from functools import reduce
from itertools import permutations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from idfold.catalog.core import params_for
from idfold.catalog.measures import _HEIGHTS, heights
from idfold.catalog.registry import EVENTS_SQL, query
from idfold.functions.hashing import universal
from idfold.operators import baselines, chain, dealt, mapping, metrics, teacher
from idfold.operators.kernel import FREQUENCY_MODES, GATES
from idfold.operators.sample_file import BLOCK, CHUNK, SampleFile, Streamed, fit
from idfold.operators.student import ModelParams, auc, init_model, score
from idfold.plans import experiments
from idfold.sources import samples as src
from idfold.storage import settle

LEARNED = FREQUENCY_MODES["weight_and_filter"]


class Words:
    """The word sample set with its vocabulary, teacher chains and training data, each written once.

    The teacher is the click model at width 2 (or 4), trained on all samples of its days and counted
    in the same pass; ``control_rate`` takes the exact label rate per word instead.
    """

    def __init__(self, spark, sf_dir: str, *, drop: int = 100, days: int = 8):
        self.samples = settle(src.word_samples(spark, sf_dir, drop=drop, days=days))
        self.vocab = settle(self.samples.select(F.col("ids")[0].alias("id")).distinct().withColumn("feature", F.lit("word")))
        self.n = self.vocab.count()

    def data(self, train_days=(src.STUDENT_DAY, src.STUDENT_DAY), eval_days=(src.EVAL_DAY,)) -> DataFrame:
        return settle(experiments.aggregated(self.samples, train_days=train_days, eval_days=eval_days))

    def _chosen(self, lo: int, hi: int, n: int | None, seed: int) -> DataFrame:
        chosen = src.days(self.samples, lo, hi)
        return src.take(chosen, n, seed=seed) if n else chosen

    def teacher(self, lo: int = 1, hi: int = 7, n: int | None = None, *, width: int = 2, seed: int = 0) -> DataFrame:
        p = ModelParams(epochs=6, seed=seed)
        return settle(teacher.click(self._chosen(lo, hi, n, seed), feature="word", vocab=self.vocab, width=width, params=p))

    def control_rate(self) -> DataFrame:
        return settle(teacher.rate(self._chosen(1, 7, None, 0), feature="word", vocab=self.vocab))

    def chain(self, taught: DataFrame, dims: int = 1, first: int = 0) -> DataFrame:
        """Chains of ``dims`` latent dimensions from ``first`` on."""
        cut = taught.withColumn("vec", F.slice("vec", first + 1, dims))
        return settle(chain.build(cut))

    def learned(self, c: DataFrame, size_pct: float, mode: str = "weight_and_filter", n: int | None = None, **more) -> DataFrame:
        m = {"stride": 0.05} | FREQUENCY_MODES[mode] | more
        return mapping.emit(c, chain.fold_local(c, replace(params_for(n or self.n, budget=size_pct / 100, **m), micro=False)))

    def rows(self, size_pct: float) -> int:
        return max(1, math.ceil(self.n * size_pct / 100))


def _cells(maps: dict[str, DataFrame]) -> DataFrame:
    parts = [m.select(F.lit(cell).alias("cell"), F.col("slot").cast("int").alias("slot"), "id", F.col("row").cast("long").alias("row")) for cell, m in maps.items()]
    return settle(reduce(DataFrame.unionByName, parts))


def _run(w: Words, maps: dict[str, DataFrame], *, reps: int = 2, train_days=(src.STUDENT_DAY, src.STUDENT_DAY), eval_days=(src.EVAL_DAY,), own=None) -> DataFrame:
    results = settle(experiments.run_cells(w.data(train_days, eval_days), _cells(maps), reps=reps, own=own))
    keys = ["part"] if len(eval_days) > 1 else []
    return experiments.report(results, *keys).withColumn("size_pct", F.round(100.0 * F.col("rows") / w.n, 3))


SIZES = (75, 50, 30, 20, 15, 10, 5, 2, 1)


@query("wl_fig1")
def wl_fig1(spark, sf_dir):
    """Quality against size for hashing: modulo and random."""
    w = Words(spark, sf_dir)
    maps = {"full": baselines.identity(w.vocab)}
    for pct in SIZES:
        maps[f"modulo_{pct}"] = baselines.modulo(w.vocab, w.rows(pct))
        maps[f"random_{pct}"] = baselines.hashed(w.vocab, w.rows(pct))
    return _run(w, maps)


class Orders:
    """Order lines with the planted label and four id features; the teacher is trained on all jointly."""

    FEATURES = ("part", "customer", "supplier", "nation")

    def __init__(self, spark, sf_dir: str):
        raw = src.order_samples(spark, sf_dir)
        x = [F.col(f) for f in self.FEATURES]
        # Written once, for all models; there is a sample per line at most, unless keys of other tables repeat.
        self.samples = dealt.deal(raw, x=x, label=F.col("planted"), day=F.col("day"), key=[F.col("sample_id")], n=src.table(spark, sf_dir, "lineitem").count())
        top = self.samples.agg(F.sum("early").alias("early"), *[(F.max(F.get("top", F.lit(k))) + 1).alias(f) for k, f in enumerate(self.FEATURES)]).first()
        self.heights, self.early = {f: int(top[f]) for f in self.FEATURES}, int(top["early"])

    def teacher(self, width: int = 2) -> DataFrame:
        return settle(teacher.deep_dealt(self.samples, features=list(self.FEATURES), heights=self.heights, days=src.TEACHER_DAYS, width=width, epochs=4, batch=2048))

    def budget(self, f: str, pct: float) -> int:
        """Rows of a folded table; multiples of 97 would show the hidden scores to modulo hashing."""
        m = max(1, math.ceil(self.heights[f] * pct / 100))
        return m + 1 if m % 97 == 0 else m

    def cell(self, name: str, method: str, pct: float, *, skip: int = 0, slots: int = 1, chains: DataFrame | None = None) -> DataFrame:
        """(cell, feature, id, an array of rows): the map of every feature; slots follow each other in one table."""
        spark, parts = self.samples.sparkSession, []
        for k, f in enumerate(self.FEATURES):
            m, ids = max(1, self.budget(f, pct) // slots), spark.range(self.heights[f])
            if method == "full" or self.heights[f] < skip:
                rows = ids.select("id", F.array("id").alias("rows"))
            elif method == "modulo":
                rows = ids.select("id", F.array(F.pmod("id", F.lit(m))).alias("rows"))
            elif method == "random":
                rows = ids.select("id", F.array(*[universal(F.col("id"), m, seed=s) + s * m for s in range(slots)]).alias("rows"))
            else:
                c = chains.where((F.col("feature") == f) & (F.col("dim") < slots))
                p = replace(params_for(self.heights[f], stride=0.05, **LEARNED), row_budget=m, size_cap=max(1, math.ceil(4 * self.heights[f] / m)), micro=False)
                rows = mapping.emit(c, chain.fold_local(c, p)).groupBy("id").agg(F.transform(F.array_sort(F.collect_list(F.struct("slot", "row"))), lambda x: x["row"] + x["slot"] * m).alias("rows"))
            parts.append(rows.select(F.lit(name).alias("cell"), F.lit(k).alias("feature"), "id", F.col("rows").cast("array<int>").alias("rows")))
        return reduce(DataFrame.unionByName, parts)

    def run(self, cells: list[DataFrame], *, reps: int = 2, epochs: int = 6) -> DataFrame:
        """Mean AUC on day 8 of the click model trained on days 1-7 (few order lines a day).

        A task trains one model: it gets the map of its cell, then passes over the one copy of the
        samples, which it reads from the shared folder: one that tells the ids in use (and holds the
        samples, if they are a block at most), one per epoch otherwise, and one to score day 8.
        """
        heights = [self.heights[f] for f in self.FEATURES]
        maps = settle(reduce(DataFrame.unionByName, cells))
        names = sorted(r["cell"] for r in maps.select("cell").distinct().collect())
        whole, record = self.early <= BLOCK, dealt.kind(len(heights))
        per = 3 + (0 if whole else epochs)  # steps of a model: the map, the ids, epochs, scores
        streams = []
        for k in range(len(names) * reps):
            entries = maps.where(F.col("cell") == names[k // reps]).select(F.lit(k * per).alias("step"), "feature", F.col("id").cast("int").alias("id"), "rows", F.lit(None).cast("binary").alias("samples"))
            streams.append(dealt.in_one([entries, *dealt.passes(self.samples, range(k * per + 1, (k + 1) * per))]))

        def fit_cells(batches):
            steps, rows = dealt.Steps(), []

            def columns(s):
                return [t[ids].astype(np.int64) for t, ids in zip(rows, s["x"].T)]

            for step, stream in dealt.by_group(batches, "step"):
                number, at = divmod(int(step), per)
                steps.at(step, at == 0)
                if at == 0:
                    rows = _rows_of(stream, heights)
                    early, late, used, n, epoch = SampleFile(len(heights) + 1), [], [np.zeros(h, dtype=bool) for h in heights], 0, None
                    continue
                for b in stream:
                    s = dealt.records(b["samples"], record)
                    before = s["day"] < src.EVAL_DAY
                    if at == 1:
                        for u, ids in zip(used, s["x"].T, strict=True):
                            u[ids] = True
                        n += int(before.sum())
                        if whole:
                            early.add(np.column_stack([s["x"], s["day"]])[before], s["y"][before])
                    elif at < per - 1:
                        epoch.add(s[before])
                    else:
                        s = s[s["day"] == src.EVAL_DAY]
                        late += [(part["y"], score(model, columns(part))) for part in np.split(s, range(CHUNK, len(s), CHUNK)) if len(part)]
                if at == 1:
                    sizes = [int(t[u].max()) + 1 if u.any() else 0 for t, u in zip(rows, used, strict=True)]
                    p = ModelParams(epochs=epochs, seed=number % reps, batch=max(512, n // 100))
                    model = init_model(sizes, p)
                    if whole:
                        order = lambda s: np.lexsort([*s["x"].T, s["y"], *[t[ids, 0] for t, ids in zip(rows, s["x"].T)], s["x"][:, -1]])  # noqa: B023, E731
                        fit(model, early, p, columns=columns, order=order)
                    early.close()
                    epoch = Streamed(model, n, p, columns=columns)
                elif at < per - 1:
                    epoch.end()
                else:
                    label, value = (np.concatenate([np.zeros(0), *[x[k] for x in late]]) for k in range(2))
                    if n + len(label):
                        yield pa.RecordBatch.from_pylist([{"cell": names[number // reps], "rep": number % reps, "rows": sum(sizes), "train_uses": n, "eval_uses": len(label), "auc": auc(label, value)}], schema=_RUN)

        runs = dealt.beside(streams).mapInArrow(fit_cells, "cell string, rep int, rows bigint, train_uses bigint, eval_uses bigint, auc double")
        return experiments.report(settle(runs)).withColumn("size_pct", F.round(100.0 * F.col("rows") / sum(self.heights.values()), 3))


_RUN = pa.schema([("cell", pa.string()), ("rep", pa.int32()), ("rows", pa.int64()), ("train_uses", pa.int64()), ("eval_uses", pa.int64()), ("auc", pa.float64())])


def _rows_of(stream, heights: list[int]) -> list[np.ndarray]:
    """The map of a cell as an array (ids x slots) per feature from its entries; ids without one have row -1."""
    found: list[np.ndarray | None] = [None] * len(heights)
    for b in stream:
        kinds, ids, sizes = b["feature"].to_numpy(), b["id"].to_numpy(), b["rows"].value_lengths().to_numpy()
        flat, ends = b["rows"].flatten().to_numpy(), np.cumsum(sizes)
        for k in np.unique(kinds):
            at = np.flatnonzero(kinds == k)
            slots = int(sizes[at[0]])
            if found[k] is None:
                found[k] = np.full((heights[k], slots), -1, dtype=np.int32)
            found[k][ids[at]] = flat[(ends[at] - slots)[:, None] + np.arange(slots)]
    return found


@query("wl_fig1_orders")
def wl_fig1_orders(spark, sf_dir):
    """Quality against size for hashing on order lines (planted label)."""
    o = Orders(spark, sf_dir)
    return o.run([o.cell("full", "full", 100), *[o.cell(f"modulo_{pct}", "modulo", pct) for pct in (75, 50, 30, 20, 10, 5, 2)]])


@query("wl_fig2")
def wl_fig2(spark, sf_dir):
    """Skipping short tables: the same size target with tables under 0, 100 and 1000 rows left whole."""
    o = Orders(spark, sf_dir)
    chains, cells = settle(chain.build(o.teacher())), [o.cell("full", "full", 100)]
    for cutoff in (0, 100, 1000):
        cells += [o.cell(f"{method}_skip_{cutoff}", method, 10, skip=cutoff, chains=chains) for method in ("modulo", "learned")]
    return o.run(cells)


@query("wl_fig3_orders")
def wl_fig3_orders(spark, sf_dir):
    """Learned folding from a jointly trained teacher against hashing on order lines, one and two internal tables."""
    o = Orders(spark, sf_dir)
    chains, cells = settle(chain.build(o.teacher())), [o.cell("full", "full", 100)]
    for pct in (30, 10, 5):
        cells += [o.cell(f"{method}_{pct}", method, pct, chains=chains) for method in ("learned", "modulo", "random")]
        cells.append(o.cell(f"learned_2_{pct}", "learned", pct, slots=2, chains=chains))
    return o.run(cells)


@query("wl_fig3")
def wl_fig3(spark, sf_dir):
    """Learned folding with access frequency against hashing across sizes; uncompressed models beside.

    Cells named ``_teacher_days`` train the student on the teacher's days: the map carries what the
    teacher saw in seven days, so a one-day student may gain from it. ``control_rate`` folds by the
    exact label rate instead of a trained teacher.
    """
    w = Words(spark, sf_dir)
    c, control, maps = w.chain(w.teacher()), w.chain(w.control_rate()), {"full": baselines.identity(w.vocab)}
    for pct in SIZES[1:]:
        maps[f"learned_{pct}"] = w.learned(c, pct)
        maps[f"modulo_{pct}"] = baselines.modulo(w.vocab, w.rows(pct))
        maps[f"random_{pct}"] = baselines.hashed(w.vocab, w.rows(pct))
    maps["control_rate_10"] = w.learned(control, 10)
    one_day = _run(w, maps)
    long = {"full": baselines.identity(w.vocab), "learned_10": maps["learned_10"], "modulo_10": maps["modulo_10"]}
    return one_day.unionByName(_run(w, long, train_days=src.TEACHER_DAYS).withColumn("cell", F.concat("cell", F.lit("_teacher_days"))))


@query("quality_delta")
def quality_delta(spark, sf_dir):
    """What each method is above hashing and above the uncompressed model at equal size."""
    w = Words(spark, sf_dir)
    c, maps = w.chain(w.teacher()), {"full": baselines.identity(w.vocab)}
    for pct in (20, 5):
        maps[f"learned_{pct}"], maps[f"modulo_{pct}"] = w.learned(c, pct), baselines.modulo(w.vocab, w.rows(pct))
    return metrics.quality_delta(settle(_run(w, maps)), base="modulo")


@query("wl_scores")
def wl_scores(spark, sf_dir):
    """Scores of the learned and the hashed model at 10 %, and their AUC by the exact aggregate."""
    w = Words(spark, sf_dir)
    maps = {"learned_10": w.learned(w.chain(w.teacher()), 10), "modulo_10": baselines.modulo(w.vocab, w.rows(10))}
    return metrics.auc(settle(experiments.run_scores(w.data(), _cells(maps))), keys=["cell", "part"], weight="uses")


@query("wl_fig4")
def wl_fig4(spark, sf_dir):
    """One against two internal tables at the same total size, learned (one map per latent dimension) and hashed (summed)."""
    w = Words(spark, sf_dir)
    t = w.teacher()
    c1, c2, maps = w.chain(t), w.chain(t, 2), {"full": baselines.identity(w.vocab)}
    for pct in (20, 10, 5):
        maps[f"learned_1_{pct}"] = w.learned(c1, pct)
        maps[f"learned_2_{pct}"] = w.learned(c2, pct / 2)
        maps[f"random_1_{pct}"] = baselines.hashed(w.vocab, w.rows(pct))
        maps[f"random_2_{pct}"] = baselines.hashed(w.vocab, w.rows(pct / 2), slots=2)
    return _run(w, maps)


@query("wl_fig5")
def wl_fig5(spark, sf_dir):
    """Private rows for the most used 0, 1 and 2.5 % of ids at 5 % size, learned and double hashing."""
    w = Words(spark, sf_dir)
    t = w.teacher()
    c, maps, room = w.chain(t), {}, w.rows(5)
    counts = settle(t.select("feature", "id", "accesses"))
    for pct in (0.0, 1.0, 2.5):
        private = math.ceil(w.n * pct / 100)
        half = max(1, (room - private) // 2)
        maps[f"hashed_retain_{pct}"] = _both_slots(baselines.retain_double_hash(counts, private + half, pct, second=half), w)
        if pct == 0:
            maps["learned_retain_0.0"] = w.learned(c, 5)
            continue
        kept = settle(baselines.kept_rows(counts, pct))
        rest = w.chain(t.join(kept.select("id"), "id", "left_anti"))
        n_rest = rest.count()
        maps[f"learned_retain_{pct}"] = mapping.retain(counts, w.learned(rest, 100.0 * (room - kept.count()) / n_rest, n=n_rest), kept=kept)
    return _run(w, maps)


def _both_slots(m: DataFrame, w: Words) -> DataFrame:
    """Slot-1 entries for ids that have none: a row of their own kind behind all others (a shared spare row)."""
    top = m.where("slot = 1").agg((F.max("row") + 1).alias("spare"))
    missing = m.where("slot = 0").join(m.where("slot = 1").select("id"), "id", "left_anti")
    return m.unionByName(missing.select("feature", F.lit(1).alias("slot"), "id", F.coalesce(top.scalar(), F.lit(0)).alias("row")))


@query("wl_fig6")
def wl_fig6(spark, sf_dir):
    """The four ways to use access frequency across small sizes, one internal table."""
    w = Words(spark, sf_dir)
    c = w.chain(w.teacher())
    return _run(w, {f"{mode}_{pct}": w.learned(c, pct, mode) for pct in (15, 5, 2) for mode in FREQUENCY_MODES})


@query("wl_fig7")
def wl_fig7(spark, sf_dir):
    """Frequency use with one and two internal tables, 15 % and 5 %."""
    w = Words(spark, sf_dir)
    t = w.teacher()
    c1, c2, maps = w.chain(t), w.chain(t, 2), {}
    for pct in (15, 5):
        for mode in ("none", "weight_only", "weight_and_filter"):
            maps[f"{mode}_1_{pct}"] = w.learned(c1, pct, mode)
            maps[f"{mode}_2_{pct}"] = w.learned(c2, pct / 2, mode)
    return _run(w, maps)


@query("wl_fig8")
def wl_fig8(spark, sf_dir):
    """Teacher sample count: a quarter against half of the samples of the same days."""
    w = Words(spark, sf_dir)
    n = src.days(w.samples, 1, 7).count()
    maps = {}
    for share in (4, 2):
        c = w.chain(w.teacher(n=n // share))
        for pct in (10, 2):
            maps[f"teacher_1/{share}_{pct}"] = w.learned(c, pct)
    return _run(w, maps)


@query("wl_fig9")
def wl_fig9(spark, sf_dir):
    """Teacher look-back at equal sample count: days 1-7, 5-8 (which includes the evaluation day) and 5-7."""
    w = Words(spark, sf_dir)
    n = min(src.days(w.samples, lo, hi).count() for lo, hi in ((1, 7), (5, 8), (5, 7)))
    maps = {}
    for lo, hi in ((1, 7), (5, 8), (5, 7)):
        c = w.chain(w.teacher(lo, hi, n))
        for pct in (10, 2):
            maps[f"days_{lo}-{hi}_{pct}"] = w.learned(c, pct)
    return _run(w, maps)


@query("wl_ageing")
def wl_ageing(spark, sf_dir):
    """How a map learned on days 1-7 ages: AUC of learned and hashed models on each of days 8 to 16."""
    w = Words(spark, sf_dir, days=16)
    maps = {"full": baselines.identity(w.vocab), "learned_10": w.learned(w.chain(w.teacher()), 10), "modulo_10": baselines.modulo(w.vocab, w.rows(10))}
    return _run(w, maps, reps=1, eval_days=tuple(range(8, 17)))


_SEEN = EVENTS_SQL + ", seen AS (SELECT DISTINCT user_id FROM ev WHERE day BETWEEN 1 AND 7)"


@query("wl_unseen", f"WITH {_SEEN} SELECT day, count(*) AS uses, round(avg(CASE WHEN user_id IN (SELECT user_id FROM seen) THEN 0.0 ELSE 1.0 END), 6) AS unseen_share FROM ev WHERE day >= 8 GROUP BY day")
def wl_unseen(spark, sf_dir):
    """Share of the uses of later days by users that a map of days 1-7 does not know."""
    e = src.event_samples(spark, sf_dir)
    seen = e.where("day between 1 and 7").select("user_id").distinct().withColumn("known", F.lit(1))
    later = e.where("day >= 8").groupBy("day", "user_id").agg(F.count("*").alias("n")).join(seen, "user_id", "left")
    unseen = F.sum(F.when(F.col("known").isNull(), F.col("n")).otherwise(0))
    return later.groupBy("day").agg(F.sum("n").alias("uses"), F.round(unseen / F.sum("n"), 6).alias("unseen_share"))


@query("wl_tuning")
def wl_tuning(spark, sf_dir):
    """Stride, cap and split mode, then gate orders and removals, at 10 % size: AUC per setting."""
    w = Words(spark, sf_dir)
    c, maps = w.chain(w.teacher()), {}
    for stride in (0.01, 0.25):
        for cap in (12, 40):
            for split in ("pairs", "pack"):
                maps[f"stride_{stride}_cap_{cap}_{split}"] = w.learned(c, 10, stride=stride, cap=cap, split=split)
    for k in (3, 2, 1):
        for gates in permutations(GATES, k):
            maps["gates_" + ">".join(gates)] = w.learned(c, 10, gates=gates)
    return _run(w, maps)


@query("wl_composition")
def wl_composition(spark, sf_dir):
    """Folding to 10 % of the rows composed with narrower tables and fewer bits: AUC and size in percent of width 16 at 32 bits."""
    w = Words(spark, sf_dir)
    shapes = {"full": baselines.identity(w.vocab), "learned": w.learned(w.chain(w.teacher()), 10)}
    maps, own = {}, {}
    for name, m in shapes.items():
        for width in (16, 4, 2):
            for bits in (32, 8):
                cell = "full" if (name, width, bits) == ("full", 16, 32) else f"{name}_w{width}_b{bits}"
                maps[cell], own[cell] = m, {"width": width, "bits": bits}
    share = F.create_map(*[F.lit(x) for cell, o in own.items() for x in (cell, o["width"] * o["bits"] / 512.0)])
    return _run(w, maps, own=own).withColumn("size_pct", F.round(F.col("size_pct") * share[F.col("cell")], 3))


@query("composition_size", "WITH h AS (" + _HEIGHTS + """), p AS (SELECT pct, width, bits, sum(CASE WHEN height >= 1000 THEN greatest(ceil(height * pct / 100.0), 1) ELSE height END * width * bits) AS small, sum(height * 16 * 32) AS large
FROM h, (VALUES (100), (10)) a(pct), (VALUES (16), (8), (4), (2)) b(width), (VALUES (32), (8)) c(bits) GROUP BY ALL) SELECT pct AS rows_pct, width, bits, round(100.0 * small / large, 6) AS size_pct FROM p""")
def composition_size(spark, sf_dir):
    """Size of folded, narrowed and quantised tables in percent of the original."""
    out = []
    for pct in (100, 10):
        for width in (16, 8, 4, 2):
            for bits in (32, 8):
                one = mapping.size_report(mapping.plan(heights(spark, sf_dir), size_pct=pct, skip_below=1000), width=width, bits=bits)
                out.append(one.select(F.lit(pct).alias("rows_pct"), F.lit(width).alias("width"), F.lit(bits).alias("bits"), "size_pct"))
    return reduce(DataFrame.unionByName, out)


@query("end_to_end_cost", "WITH h AS (" + _HEIGHTS + """), t AS (SELECT dims, pct, sum(height) AS ids, sum(height * dims)::BIGINT AS teacher_params,
sum(CASE WHEN height >= 1000 THEN greatest(ceil(height * pct / 100.0), 1) ELSE height END * 16)::BIGINT AS student_params, sum(height * 16)::BIGINT AS full_params, sum(CASE WHEN height >= 1000 THEN height ELSE 0 END)::BIGINT AS map_entries
FROM h, (VALUES (2), (4)) a(dims), (VALUES (30), (10), (2)) b(pct) GROUP BY ALL)
SELECT dims, pct AS rows_pct, teacher_params, student_params, map_entries, full_params, round(100.0 * greatest(teacher_params, student_params) / full_params, 6) AS peak_pct FROM t""")
def end_to_end_cost(spark, sf_dir):
    """Parameters of the teacher (full height, width 2 or 4) and of the folded student (width 16) beside the original, and the larger of both."""
    grid = spark.createDataFrame([(d, p) for d in (2, 4) for p in (30, 10, 2)], "dims int, rows_pct int")
    tall = F.col("height") >= 1000
    rows = F.when(tall, F.greatest(F.ceil(F.col("height") * F.col("rows_pct") / 100.0), F.lit(1))).otherwise(F.col("height"))
    cost = heights(spark, sf_dir).join(F.broadcast(grid)).groupBy("dims", "rows_pct").agg(
        F.sum(F.col("height") * F.col("dims")).alias("teacher_params"), F.sum(rows * 16).cast("long").alias("student_params"),
        F.sum(F.when(tall, F.col("height")).otherwise(0)).alias("map_entries"), F.sum(F.col("height") * 16).alias("full_params"),
    )
    return cost.withColumn("peak_pct", F.round(100.0 * F.greatest("teacher_params", "student_params") / F.col("full_params"), 6))


@query("wl_teacher_width")
def wl_teacher_width(spark, sf_dir):
    """Trained teachers of width 2 and 4, each of their first dimensions as the one that folds, at 10 % size."""
    w = Words(spark, sf_dir)
    maps = {"full": baselines.identity(w.vocab)}
    for width in (2, 4):
        t = w.teacher(width=width)
        for dim in range(2):
            maps[f"width_{width}_dim_{dim}"] = w.learned(w.chain(t, 1, dim), 10)
    return _run(w, maps)


@query("wl_table1", f"SELECT feature, height FROM ({_HEIGHTS})")
def wl_table1(spark, sf_dir):
    """Inventory of the id features and their heights."""
    return heights(spark, sf_dir)


@query("wl_splits", f"WITH {EVENTS_SQL} SELECT day, dayname(min(ts)) AS weekday, CASE WHEN day <= 7 THEN 'teacher' ELSE 'eval' END AS split, day = 5 AS student, count(*) AS n FROM ev WHERE day BETWEEN 1 AND 8 GROUP BY day")
def wl_splits(spark, sf_dir):
    """Rows and weekday of every day of the eight-day calendar."""
    e = src.event_samples(spark, sf_dir).where("day BETWEEN 1 AND 8")
    g = e.groupBy("day").agg(F.date_format(F.min("ts"), "EEEE").alias("weekday"), F.count("*").alias("n"))
    return g.select("day", "weekday", F.when(F.col("day") <= 7, "teacher").otherwise("eval").alias("split"), (F.col("day") == 5).alias("student"), "n")
