"""Teachers: full-height tables of very small width, with access counts.

Every teacher returns (feature, id, vec, accesses) for each id of the vocabulary.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from idfold.operators import access, dealt
from idfold.operators.dealt import by_group
from idfold.operators.sample_file import BLOCK, SampleFile, Streamed, fit
from idfold.operators.student import ModelParams, init_model, train

ALL = "__all"


def rate(samples: DataFrame, *, feature: str, ids_col: str = "ids", vocab: DataFrame | None = None, prior: float = 1.0) -> DataFrame:
    """Width 1, exact: smoothed share of positive samples per id, in micro-units.

    A deterministic stand-in for a trained teacher; unseen ids get the overall share.
    """
    long = samples.select("label", F.explode(ids_col).alias("id"))
    base = long.agg(F.avg("label").alias("p"))
    per = long.groupBy("id").agg(F.count("*").alias("accesses"), F.sum("label").alias("ones"))
    if vocab is not None:
        per = vocab.select("id").join(per, "id", "left")
    n, ones = F.coalesce("accesses", F.lit(0)), F.coalesce("ones", F.lit(0))
    p = F.coalesce(base.scalar(), F.lit(0.5))
    value = F.round(1e6 * (ones + prior * p) / (n + prior)).cast("double")
    return per.select(F.lit(feature).alias("feature"), "id", F.array(value).alias("vec"), n.cast("long").alias("accesses"))


def from_table(df: DataFrame, *, id_col: str, vec_col: str, dims: int, feature: str, accesses: DataFrame | None = None) -> DataFrame:
    """The first ``dims`` coordinates of an existing trained table."""
    t = df.select(F.lit(feature).alias("feature"), F.col(id_col).cast("long").alias("id"), F.transform(F.slice(vec_col, 1, dims), lambda x: x.cast("double")).alias("vec"))
    if accesses is None:
        return t.withColumn("accesses", F.lit(0).cast("long"))
    return t.join(accesses.select("id", "accesses"), "id", "left").select("feature", "id", "vec", F.coalesce("accesses", F.lit(0)).cast("long").alias("accesses"))


def als(pairs: DataFrame, *, user: str, item: str, width: int = 2, iterations: int = 5, seed: int = 0) -> DataFrame:
    """Matrix factorisation of implicit counts (user, item); factors of both sides as two features.

    Ids must fit an int; factors stay distributed.
    """
    from pyspark.ml.recommendation import ALS

    ratings = pairs.groupBy(F.col(user).cast("int").alias("u"), F.col(item).cast("int").alias("i")).agg(F.count("*").cast("float").alias("r"))
    model = ALS(rank=width, maxIter=iterations, userCol="u", itemCol="i", ratingCol="r", implicitPrefs=True, seed=seed).fit(ratings)
    side = lambda factors, name, col: factors.select(F.lit(name).alias("feature"), F.col("id").cast("long").alias("id"), F.transform("features", lambda x: x.cast("double")).alias("vec")).join(
        pairs.groupBy(F.col(col).cast("long").alias("id")).agg(F.count("*").alias("accesses")), "id"
    ).select("feature", "id", "vec", "accesses")
    return side(model.userFactors, user, user).unionByName(side(model.itemFactors, item, item))


def fm(samples: DataFrame, *, features: list[str], heights: dict[str, int], label: str = "label", width: int = 2, steps: int = 60, seed: int = 0) -> DataFrame:
    """Factorisation machine over features with ids 0 .. height - 1; factors per id."""
    from pyspark.ml.classification import FMClassifier
    from pyspark.ml.linalg import Vectors, VectorUDT  # noqa: F401
    from pyspark.ml.functions import array_to_vector
    from pyspark.ml.feature import OneHotEncoder, VectorAssembler

    hot = OneHotEncoder(inputCols=features, outputCols=[f"{f}_hot" for f in features], dropLast=False, handleInvalid="keep")
    typed = samples.select(F.col(label).cast("double").alias("label"), *[F.col(f).cast("double").alias(f) for f in features])
    encoder = hot.fit(typed)
    data = VectorAssembler(inputCols=hot.getOutputCols(), outputCol="x").transform(encoder.transform(typed)).select("label", "x")
    model = FMClassifier(featuresCol="x", labelCol="label", factorSize=width, maxIter=steps, stepSize=0.05, seed=seed).fit(data)
    factors, rows, at = model.factors.toArray(), [], 0
    for f, size in zip(features, encoder.categorySizes, strict=True):
        rows += [(f, i, [float(x) for x in factors[at + i]]) for i in range(int(size))]
        at += int(size) + 1  # one slot for ids not seen when fitting
    table = samples.sparkSession.createDataFrame(rows, "feature string, id bigint, vec array<double>")
    counts = access.count(samples.withColumn("sample_id", F.lit(0)), features=features)
    return table.join(counts, ["feature", "id"], "left").select("feature", "id", "vec", F.coalesce("accesses", F.lit(0)).cast("long").alias("accesses"))


def _taught(feature: str, table: np.ndarray, ids, uses: np.ndarray, rows: int = 10_000):
    """Arrow batches (feature, id, vec, accesses) of one trained table."""
    width = table.shape[1]
    for at in range(0, len(table), rows):
        part = table[at : at + rows]
        vec = pa.ListArray.from_arrays(pa.array(np.arange(0, part.size + 1, width), pa.int32()), pa.array(part.reshape(-1), pa.float64()))
        columns = [pa.array([feature] * len(part)), pa.array(ids[at : at + rows], pa.int64()), vec, pa.array(uses[at : at + rows], pa.int64())]
        yield pa.RecordBatch.from_arrays(columns, names=["feature", "id", "vec", "accesses"])


TAUGHT = "feature string, id bigint, vec array<double>, accesses bigint"


def click(samples: DataFrame, *, feature: str, vocab: DataFrame, width: int = 2, params: ModelParams | None = None, label: str = "label", ids_col: str = "ids") -> DataFrame:
    """Trained teacher of one feature: the click model at tiny width over all samples of single ids.

    Samples of one id and label are counted first, which also gives the access counts, so the one
    task that trains the model sees at most two rows per id; ids without a sample keep their start.
    Its memory is some 70 bytes an id: the ids, their uses and the table.
    """
    p = params or ModelParams(epochs=6)
    p = ModelParams(**{**p.__dict__, "width": width})
    groups = samples.select(F.col(ids_col)[0].alias("id"), F.col(label).cast("int").alias("label")).groupBy("id").agg(
        F.count(F.when(F.coalesce("label", F.lit(0)) != 1, 1)).alias("zeros"), F.count(F.when(F.col("label") == 1, 1)).alias("ones")
    )
    known = vocab.select("id").join(groups, "id", "left").select("id", F.coalesce("zeros", F.lit(0)).alias("zeros"), F.coalesce("ones", F.lit(0)).alias("ones"))

    def run(batches):
        held = [(b["id"].to_numpy(), b["zeros"].to_numpy(), b["ones"].to_numpy()) for b in batches]
        if not held:
            return
        ids, zeros, ones = (np.concatenate([h[k] for h in held]) for k in range(3))
        del held
        # A row per id and label with uses, in order of id and label.
        uses = np.stack([zeros, ones], axis=1).reshape(-1)
        seen = np.flatnonzero(uses)
        model = init_model([len(ids)], p)
        train(model, [(seen >> 1).reshape(-1, 1)], seen & 1, uses[seen].astype(float), p)
        yield from _taught(feature, model["tables"][0], ids, zeros + ones)

    return known.repartition(1).sortWithinPartitions("id").mapInArrow(run, TAUGHT)


def deep(samples: DataFrame, *, features: list[str], heights: dict[str, int], width: int = 2, epochs: int = 2, label: str = "label", seed: int = 0, batch: int = 32768) -> DataFrame:
    """Click model of tiny width trained over all features jointly, in one task.

    ``samples`` holds id or id-array columns with ids 0 .. height - 1. Returns each id's vector and
    its uses. Samples are dealt once into the shared folder and read from there epoch by epoch
    (``dealt``; shorter arrays are filled up with -1), so its memory is that of the tables, a block
    and a batch, and no file of its own grows with them. Tables that do not fit a task: ``synchronous``.
    """
    kinds = dict(samples.dtypes)
    arrays = [f for f in features if kinds[f].startswith("array")]
    longest = samples.agg(*[F.max(F.size(f)).alias(f) for f in arrays]).first().asDict() if arrays else {}
    widths = [max(1, longest.get(f, 1) or 1) for f in features]
    x = [F.coalesce(F.get(f, F.lit(k)), F.lit(-1)) if f in arrays else F.col(f) for f, n in zip(features, widths, strict=True) for k in range(n)]
    key = [F.col(c) for c in ("sample_id", label, *features) if c in samples.columns]
    held = dealt.deal(samples, x=x, label=F.col(label), key=key, n=samples.count())
    return deep_dealt(held, features=features, heights=heights, widths=widths, width=width, epochs=epochs, seed=seed, batch=batch)


def deep_dealt(
    samples: DataFrame, *, features: list[str], heights: dict[str, int], widths: list[int] | None = None, days: tuple[int, int] | None = None,
    width: int = 2, epochs: int = 2, seed: int = 0, batch: int = 32768,
) -> DataFrame:
    """``deep`` over samples that ``dealt.deal`` has written, those of ``days`` only."""
    params = ModelParams(width=width, epochs=epochs, seed=seed, batch=batch)
    widths = widths or [1] * len(features)
    cuts, record = np.concatenate([[0], np.cumsum(widths)]), dealt.kind(sum(widths))
    # Sets that may hold no more than a block need the first pass only: they are held whole.
    more = epochs if (samples.agg(F.sum("n")).first()[0] or 0) > BLOCK else 0

    def bag(x: np.ndarray):
        return x.astype(np.int64) if x.min() >= 0 else [r[r >= 0] for r in x]

    def columns(s: np.ndarray) -> list:
        return [bag(s["x"][:, lo:hi]) for lo, hi in zip(cuts, cuts[1:])]

    def run(batches):
        uses, whole, n, steps = [np.zeros(heights[f], dtype=np.int64) for f in features], SampleFile(int(cuts[-1])), 0, dealt.Steps()
        model, epoch = init_model([heights[f] for f in features], params), None
        for step, stream in by_group(batches, "step"):
            steps.at(step, step == 0)
            for b in stream:
                s = dealt.records(b["samples"], record)
                s = s if days is None else s[(s["day"] >= days[0]) & (s["day"] <= days[1])]
                if step:
                    if epoch:
                        epoch.add(s)
                    continue
                n += len(s)
                if n <= BLOCK:
                    whole.add(s["x"], s["y"])
                for seen, lo, hi in zip(uses, cuts, cuts[1:]):
                    flat = s["x"][:, lo:hi].reshape(-1)
                    seen += np.bincount(flat[flat >= 0], minlength=len(seen))
            if step == 0 and n > BLOCK:
                whole.close()
                epoch = Streamed(model, n, params, columns=columns)
            elif epoch:
                epoch.end()
        if not n:
            return
        if epoch:
            if steps.last != epochs:
                raise RuntimeError(f"{steps.last} of {epochs} epochs came")
            epoch.done()
        else:
            # A canonical order of the samples: results do not depend on how rows arrive.
            order = lambda s: np.lexsort([*s["x"].T, s["y"], *[s["x"][:, k] for k in cuts[:-1]]])
            fit(model, whole, params, columns=columns, order=order)
        for f, tab, seen in zip(features, model["tables"], uses, strict=True):
            yield from _taught(f, tab, np.arange(heights[f]), seen)

    return dealt.in_one(dealt.passes(samples, range(1 + more))).mapInArrow(run, TAUGHT)


def synchronous(samples: DataFrame, *, features: list[str], width: int = 2, steps: int = 8, label: str = "label", seed: int = 0) -> DataFrame:
    """The same model with tables and samples spread over the cluster; only ids with a sample are returned."""
    from idfold.plans import synchronous as sync

    tables, _ = sync.train(samples, features=features, params=ModelParams(width=width, seed=seed), steps=steps, label=label)
    name = F.array(*[F.lit(f) for f in features])
    return tables.select(F.get(name, F.col("k")).alias("feature"), "id", "vec", "accesses")
