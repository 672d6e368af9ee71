"""Samples that many tasks read whole, several times each, from one copy in the shared folder.

The samples are dealt by a hash to blocks, packed into short binary records and written once. A task
then reads them through Spark as often as it has passes to make: the scans of its passes follow each
other in one partition, so nothing is shuffled, sorted or kept in a file of the task, and the disk
holds one copy however many models train from it.
"""

from __future__ import annotations

from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from idfold.operators.sample_file import BLOCK
from idfold.storage import settle

#: Samples of a packed row: an Arrow batch of 10,000 rows stays at some 25 MB.
PACK = 128
#: Day of samples without one.
NO_DAY = 100


def kind(width: int) -> np.dtype:
    return np.dtype([("x", "<i4", (width,)), ("y", "i1"), ("day", "i1")])


def deal(samples: DataFrame, *, x: list[Column], label: Column, day: Column | None = None, key: list[Column], n: int) -> DataFrame:
    """(n, early, top, samples): packed samples, how many there are, how many before day 8, and the greatest ``x``.

    ``key`` tells samples apart, ``n`` is about their number. Which samples a block holds, and their
    order in it, follow from the samples and ``n`` alone.
    """
    blocks = max(1, -(-n // BLOCK))
    ids = [f"x{k}" for k in range(len(x))]
    day = F.lit(0) if day is None else F.when(day.isNull(), NO_DAY).otherwise(F.greatest(F.least(day, F.lit(9)), F.lit(-1)))
    keys = [c.alias(f"key{k}") for k, c in enumerate(key)]
    rows = samples.select(*keys, *[c.cast("int").alias(i) for c, i in zip(x, ids, strict=True)], label.cast("int").alias("y"), day.cast("int").alias("day"))
    h = F.xxhash64(*[f"key{k}" for k in range(len(key))])
    dealt = rows.repartitionById(blocks, F.pmod(h, F.lit(blocks)).cast("int")).sortWithinPartitions(h, "y", *ids).select(*ids, "y", "day")
    held = kind(len(x))

    def pack(batches):
        for b in batches:
            if not b.num_rows:
                continue
            out = np.empty(b.num_rows, dtype=held)
            out["x"] = np.column_stack([b[i].to_numpy(zero_copy_only=False) for i in ids])
            out["y"], out["day"] = b["y"].to_numpy(zero_copy_only=False), b["day"].to_numpy(zero_copy_only=False)
            parts = [out[k : k + PACK] for k in range(0, len(out), PACK)]
            columns = [
                pa.array([len(p) for p in parts], pa.int32()), pa.array([int((p["day"] < 8).sum()) for p in parts], pa.int32()),
                pa.array([p["x"].max(axis=0).tolist() for p in parts], pa.list_(pa.int32())), pa.array([p.tobytes() for p in parts], pa.binary()),
            ]
            yield pa.RecordBatch.from_arrays(columns, names=["n", "early", "top", "samples"])

    return settle(dealt.mapInArrow(pack, "n int, early int, top array<int>, samples binary"))


def passes(dealt: DataFrame, steps: range) -> list[DataFrame]:
    """(step, samples): all samples once per step."""
    return [dealt.select(F.lit(s).alias("step"), "samples") for s in steps]


def in_one(parts: list[DataFrame]) -> DataFrame:
    """The rows of ``parts``, one after another, in one partition, without a shuffle."""
    return reduce(lambda a, b: a.unionByName(b, allowMissingColumns=True), parts).coalesce(1)


def beside(streams: list[DataFrame]) -> DataFrame:
    """The partitions of all ``streams``: an empty range keeps the union from joining those of one partition."""
    none = streams[0].sparkSession.range(0).select(*[F.lit(None).cast(t).alias(c) for c, t in streams[0].dtypes])
    return reduce(DataFrame.unionByName, [*streams, none])


def records(column: pa.Array, held: np.dtype) -> np.ndarray:
    """The samples of a column of packed ones; read-only."""
    _, ends, data = column.buffers()
    ends = np.frombuffer(ends, np.int32)[column.offset : column.offset + len(column) + 1]
    return np.frombuffer(data, np.uint8)[ends[0] : ends[-1]].view(held)


def by_group(batches, column: str):
    """(value, batches) of each run of equal values of ``column`` in a stream sorted by it; exhaust one before the next."""
    held = None

    def parts():
        for b in batches:
            x = b[column].to_numpy(zero_copy_only=False)
            cuts = [0, *(np.flatnonzero(x[1:] != x[:-1]) + 1).tolist(), len(x)]
            for lo, hi in zip(cuts, cuts[1:]):
                if hi > lo:
                    yield x[lo], b.slice(lo, hi - lo)

    stream = parts()
    held = next(stream, None)

    def run(value):
        nonlocal held
        while held is not None and held[0] == value:
            batch, held = held[1], None
            yield batch
            held = next(stream, None)

    while held is not None:
        value = held[0]
        yield value, run(value)


class Steps:
    """Refuses passes that come out of turn: a pass that is missed or mixed up would train another model."""

    def __init__(self):
        self.last = None

    def at(self, step: int, first: bool) -> None:
        if not first and step != self.last + 1:
            raise RuntimeError(f"pass {step} came after {self.last}")
        self.last = step
