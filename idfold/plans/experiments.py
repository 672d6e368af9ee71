"""Grids of student models over folded samples, one group per model.

A cell is (method, size, slots, mode, rep, ...). Samples of one id are first aggregated to
(id, label, uses), so a cell sees as many rows as there are distinct ids, however many samples; the
fold map of a cell turns ids into rows by a join; every cell then trains in its own task, which reads
its rows from a file of its own in blocks (``idfold.operators.sample_file``).
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from idfold.operators.dealt import by_group
from idfold.operators.sample_file import CHUNK, SampleFile, fields, fit, scores
from idfold.operators.student import ModelParams, auc, init_model, score

RESULT = "cell string, rep int, part string, rows bigint, train_uses bigint, eval_uses bigint, auc double"
SCORES = "cell string, rep int, part string, label int, uses bigint, score double"


def aggregated(samples: DataFrame, *, train_days: tuple[int, int], eval_days: tuple[int, ...]) -> DataFrame:
    """(part, id, label, uses) of one-word samples; part is train, or the day for evaluation."""
    train = F.when(F.col("day").between(*train_days), F.lit("train"))
    test = F.when(F.col("day").isin(*eval_days), F.col("day").cast("string"))
    parts = F.explode(F.array_compact(F.array(train, test))).alias("part")
    return samples.select(F.col("ids")[0].alias("id"), "label", parts).groupBy("part", "id", "label").agg(F.count("*").alias("uses"))


class _Cell:
    """The samples of one cell by part, in files, and the sizes of its internal tables."""

    def __init__(self, batches):
        self.parts: dict[str, SampleFile] = {}
        self.top = None
        for b in batches:
            rows = b["rows"].flatten().to_numpy().reshape(b.num_rows, -1)
            self.top = rows.max(axis=0) if self.top is None else np.maximum(self.top, rows.max(axis=0))
            part, label, uses = b["part"].to_numpy(zero_copy_only=False), b["label"].to_numpy(), b["uses"].to_numpy()
            for name in np.unique(part):
                at = part == name
                self.parts.setdefault(name, SampleFile(rows.shape[1])).add(rows[at], label[at], uses[at])
        self.offset = np.concatenate([[0], np.cumsum(self.top + 1)])
        self.rows = int(self.offset[-1])
        self.train = self.parts.pop("train", None) or SampleFile(len(self.top))

    def columns(self, samples: np.ndarray) -> list[np.ndarray]:
        """One table; a bag of a row per slot sums the internal tables."""
        return [samples["x"] + self.offset[:-1]]

    def fitted(self, p: ModelParams) -> dict:
        # A canonical order of the groups: results do not depend on how rows arrive.
        model = init_model([self.rows], p)
        fit(model, self.train, p, columns=self.columns, order=lambda s: np.lexsort([s["w"], s["y"], *s["x"].T]))
        return model

    def close(self) -> None:
        for held in (self.train, *self.parts.values()):
            held.close()


def _by_cell(data: DataFrame, maps: DataFrame) -> tuple[DataFrame, list[str]]:
    """(at, part, label, uses, rows): a partition per cell, sorted by a hash, and the names of the cells."""
    cells = sorted(r["cell"] for r in maps.select("cell").distinct().collect())
    slots = maps.groupBy("cell", "id").agg(F.array_sort(F.collect_list(F.struct("slot", "row"))).alias("r"))
    wide = slots.select("cell", "id", F.transform("r", lambda x: x["row"].cast("int")).alias("rows"))
    at = F.array_position(F.array(*[F.lit(c) for c in cells]), F.col("cell")).cast("int") - 1
    joined = wide.join(data, "id").select(at.alias("at"), "part", F.col("label").cast("int").alias("label"), F.col("uses").cast("long").alias("uses"), "rows", F.xxhash64("part", "id", "label").alias("h"))
    return joined.repartitionById(max(1, len(cells)), F.col("at")).sortWithinPartitions("at", "h").drop("h"), cells


def run_cells(data: DataFrame, maps: DataFrame, *, reps: int = 2, params: ModelParams | None = None, own: dict[str, dict] | None = None) -> DataFrame:
    """AUC per (cell, rep) and evaluation part. ``data``: part, id, label, uses; ``maps``: cell, slot, id, row.

    Cells with several slots sum their internal tables (same gradient to each). Uses act as sample
    weights. ``own`` changes parameters of single cells (width, bits).
    """
    base, own = params or ModelParams(epochs=6), own or {}
    joined, cells = _by_cell(data, maps)

    def run(batches):
        for at, stream in by_group(batches, "at"):
            cell, out = _Cell(stream), []
            train_uses = int(fields(cell.train, "w").sum(dtype=np.int64))
            for rep in range(reps):
                model = cell.fitted(ModelParams(**{**base.__dict__, **own.get(cells[at], {}), "seed": rep}))
                for name, held in sorted(cell.parts.items()):
                    uses = fields(held, "w")
                    value = auc(fields(held, "y"), scores(model, held, columns=cell.columns), uses.astype(float))
                    out.append((cells[at], rep, name, cell.rows, train_uses, int(uses.sum(dtype=np.int64)), value))
            cell.close()
            if out:
                kinds = [pa.string(), pa.int32(), pa.string(), pa.int64(), pa.int64(), pa.int64(), pa.float64()]
                columns = [pa.array(c, k) for c, k in zip(zip(*out), kinds, strict=True)]
                yield pa.RecordBatch.from_arrays(columns, names=["cell", "rep", "part", "rows", "train_uses", "eval_uses", "auc"])

    return joined.mapInArrow(run, RESULT)


def run_scores(data: DataFrame, maps: DataFrame, *, reps: int = 1, params: ModelParams | None = None) -> DataFrame:
    """The scores behind ``run_cells``: one row per group of equal samples of the evaluation parts."""
    base = params or ModelParams(epochs=6)
    joined, cells = _by_cell(data, maps)

    def run(batches):
        for at, stream in by_group(batches, "at"):
            cell = _Cell(stream)
            for rep in range(reps):
                model = cell.fitted(ModelParams(**{**base.__dict__, "seed": rep}))
                for name, held in sorted(cell.parts.items()):
                    for b in held.blocks(CHUNK):
                        n = len(b)
                        columns = [pa.array([cells[at]] * n), pa.array([rep] * n, pa.int32()), pa.array([name] * n), pa.array(b["y"], pa.int32()), pa.array(b["w"], pa.int64()), pa.array(score(model, cell.columns(b)))]
                        yield pa.RecordBatch.from_arrays(columns, names=["cell", "rep", "part", "label", "uses", "score"])
            cell.close()

    return joined.mapInArrow(run, SCORES)


def report(results: DataFrame, *keys: str) -> DataFrame:
    """Mean AUC and its spread per cell, and what it is above the uncompressed cell ``full`` (null without one)."""
    mean = results.groupBy("cell", *keys).agg(
        F.max("rows").alias("rows"), F.max("train_uses").alias("train_uses"), F.max("eval_uses").alias("eval_uses"), F.count("auc").alias("reps"),
        F.round(F.avg("auc"), 6).alias("mean_auc"), F.round(F.min("auc"), 6).alias("min_auc"), F.round(F.max("auc"), 6).alias("max_auc"),
    )
    full = F.max(F.when(F.col("cell") == "full", F.col("mean_auc"))).over(Window.partitionBy(*keys) if keys else Window.partitionBy(F.lit(1)))
    return mean.withColumn("delta_full", F.round(F.col("mean_auc") - full, 6))
