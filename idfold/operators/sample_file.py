"""Training over samples that lie in a file of the task, read in blocks.

A task gets its samples as a stream of Arrow batches, writes them to an unnamed local file and trains
any number of models from it. Memory is that of one block and one batch beside the model's tables,
however many samples there are. Samples of at most ``BLOCK`` are held whole, put into a canonical
order and drawn from by one permutation an epoch; larger sets are stored in the order they arrive
in (the callers sort by a hash), and an epoch permutes the blocks and the samples of each block.
"""

from __future__ import annotations

import os
import tempfile
from collections.abc import Callable, Iterator

import numpy as np

from idfold.operators.student import ModelParams, quantized, score, train, train_batch

BLOCK = 1 << 20
#: Samples scored at once.
CHUNK = 1 << 16


class SampleFile:
    """Samples as records (x: ids or rows, y: label, w: uses) in a local file that vanishes with the task."""

    def __init__(self, width: int):
        self.kind = np.dtype([("x", "<i4", (width,)), ("y", "i1"), ("w", "<i4")])
        folder = os.environ.get("SPARK_LOCAL_DIRS", "").split(",")[0]  # set in Spark's workers
        self.file, self.n = tempfile.TemporaryFile(dir=folder if os.path.isdir(folder) else None), 0

    def add(self, x: np.ndarray, y: np.ndarray, w: np.ndarray | int = 1) -> None:
        if not len(y):
            return
        if max(x.max(), np.max(w)) > np.iinfo(np.int32).max:
            raise ValueError("ids, rows and uses of a sample must fit 32 bits")
        out = np.empty(len(y), dtype=self.kind)
        out["x"], out["y"], out["w"] = x, y, w
        self.file.seek(0, 2)
        self.file.write(out.tobytes())
        self.n += len(y)

    def read(self, start: int, count: int) -> np.ndarray:
        self.file.seek(start * self.kind.itemsize)
        return np.frombuffer(self.file.read(count * self.kind.itemsize), dtype=self.kind)

    def blocks(self, size: int) -> Iterator[np.ndarray]:
        for start in range(0, self.n, size):
            yield self.read(start, size)

    def close(self) -> None:
        self.file.close()


def fit(model: dict, samples: SampleFile, p: ModelParams, *, columns: Callable, order: Callable) -> None:
    """Mini-batch training in place. ``columns`` turns records into columns of ids, ``order`` sorts a whole set."""
    n = samples.n
    if n <= BLOCK:
        if n:
            whole = samples.read(0, n)
            whole = whole[order(whole)]
            train(model, columns(whole), whole["y"].astype(np.int64), whole["w"].astype(float), p)
        return
    rng, size = np.random.default_rng(p.seed + 1), p.batch_of(n)
    step = size * max(1, BLOCK // size)
    for _ in range(p.epochs):
        for start in rng.permutation(np.arange(0, n, step)):
            block = samples.read(int(start), step)
            at = rng.permutation(len(block))
            for k in range(0, len(block), size):
                part = block[at[k : k + size]]
                train_batch(model, columns(part), part["y"].astype(np.int64), part["w"].astype(float), p)
    if p.bits < 32:
        model["tables"] = [quantized(t, p.bits) for t in model["tables"]]


class Streamed:
    """``fit`` for ``n`` samples, more than a block, that are handed over epoch by epoch instead of read from a file."""

    def __init__(self, model: dict, n: int, p: ModelParams, *, columns: Callable):
        self.model, self.p, self.columns = model, p, columns
        self.rng, self.size = np.random.default_rng(p.seed + 1), p.batch_of(n)
        self.step, self.held, self.n = self.size * max(1, BLOCK // self.size), [], 0

    def add(self, samples: np.ndarray) -> None:
        self.held.append(samples)
        self.n += len(samples)
        while self.n >= self.step:
            block = np.concatenate(self.held)
            self.held, self.n = [block[self.step :]], self.n - self.step
            self._train(block[: self.step])

    def end(self) -> None:
        """The epoch is over."""
        if self.n:
            self._train(np.concatenate(self.held))
        self.held, self.n = [], 0

    def done(self) -> None:
        if self.p.bits < 32:
            self.model["tables"] = [quantized(t, self.p.bits) for t in self.model["tables"]]

    def _train(self, block: np.ndarray) -> None:
        at = self.rng.permutation(len(block))
        for k in range(0, len(block), self.size):
            part = block[at[k : k + self.size]]
            train_batch(self.model, self.columns(part), part["y"].astype(np.int64), np.ones(len(part)), self.p)


def scores(model: dict, samples: SampleFile, *, columns: Callable) -> np.ndarray:
    """The score of every sample, in the order of the file."""
    return np.concatenate([np.zeros(0), *[score(model, columns(b)) for b in samples.blocks(CHUNK)]])


def fields(samples: SampleFile, name: str) -> np.ndarray:
    """One field of all samples."""
    return np.concatenate([np.zeros(0, dtype=samples.kind[name]), *[b[name].copy() for b in samples.blocks(CHUNK)]])
