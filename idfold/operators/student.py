"""The click model: embedding bags, pairwise dot products, a small dense net, log loss.

Tables use a row-wise adaptive rate (one accumulator per row, the mean squared gradient over its
width); dense layers use Adam moments with the step scaled per layer. Everything here is NumPy on one
model at a time: grids of models are parallel over groups, see ``idfold.plans.experiments``; one
model too large for a task is trained by ``idfold.plans.synchronous`` with the same formulas.

A column of ids is a two-dimensional array (samples x bag, all bags of one size) or a list of lists.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np


@dataclass(frozen=True)
class ModelParams:
    width: int = 4
    hidden: int = 8
    table_rate: float = 0.02
    dense_rate: float = 0.002
    batch: int = 32768
    epochs: int = 2
    seed: int = 0
    #: Bits of a table entry after training; 32 leaves entries as they are.
    bits: int = 32

    def batch_of(self, n: int) -> int:
        """At most a sixteenth of the samples, so that small sets still take several steps."""
        return max(16, min(self.batch, -(-n // 16)))


def init_dense(features: int, p: ModelParams, rng: np.random.Generator) -> list[np.ndarray]:
    n_in = features * p.width + features * (features - 1) // 2
    return [rng.normal(0, 1 / np.sqrt(n_in), (n_in, p.hidden)), np.zeros(p.hidden), rng.normal(0, 1 / np.sqrt(p.hidden), (p.hidden, 1)), np.zeros(1)]


def init_model(heights: list[int], p: ModelParams) -> dict:
    rng = np.random.default_rng(p.seed)
    return {
        "tables": [rng.normal(0, 0.05, (h, p.width)) for h in heights],
        "acc": [np.zeros(h) for h in heights],
        "dense": init_dense(len(heights), p, rng),
        "moments": None,
        "t": 0,
    }


def _rows(column, at: np.ndarray):
    return column[at] if isinstance(column, np.ndarray) else [column[i] for i in at]


def _flatten(ids) -> tuple[np.ndarray, np.ndarray, int | None]:
    """All ids, the sample each belongs to, and the size of the bags if all are equal."""
    if isinstance(ids, np.ndarray):
        return ids.reshape(-1), np.repeat(np.arange(len(ids)), ids.shape[1]), ids.shape[1]
    lengths = np.fromiter((len(x) for x in ids), dtype=np.int64, count=len(ids))
    flat = np.concatenate([np.asarray(x, dtype=np.int64) for x in ids]) if len(ids) else np.array([], dtype=np.int64)
    return flat, np.repeat(np.arange(len(ids)), lengths), None


def scatter_grad(grad: np.ndarray, rows: np.ndarray, height: int, how: str = "sum", slot: int = 0, slots: int = 1) -> np.ndarray:
    """Gradient of one internal table: all of it for sum, the slot's slice for concat, summed per row."""
    part = grad if how == "sum" else np.split(grad, slots, axis=1)[slot]
    return np.stack([np.bincount(rows, part[:, j], height) for j in range(part.shape[1])], axis=1)


def _pooled(table: np.ndarray, bag: tuple[np.ndarray, np.ndarray, int | None], n: int) -> np.ndarray:
    flat, owner, size = bag
    if size is not None:
        return table[flat].reshape(n, size, table.shape[1]).sum(axis=1)
    return scatter_grad(table[flat], owner, n)


def forward(e: list[np.ndarray], dense: list[np.ndarray]):
    """Pairs, input, hidden layer and logits from the pooled vectors of every feature."""
    pairs = [(i, j) for i in range(len(e)) for j in range(i + 1, len(e))]
    x = np.concatenate(e + [np.sum(e[i] * e[j], axis=1, keepdims=True) for i, j in pairs], axis=1)
    w1, b1, w2, b2 = dense
    h = np.maximum(x @ w1 + b1, 0)
    return pairs, x, h, (h @ w2 + b2)[:, 0]


def backward(e: list[np.ndarray], dense: list[np.ndarray], label: np.ndarray, share: np.ndarray) -> tuple[list[np.ndarray], list[np.ndarray]]:
    """Gradients of the pooled vectors and of the dense layers; ``share`` weighs the samples, summing to one over the batch."""
    pairs, x, h, z = forward(e, dense)
    w1, _, w2, _ = dense
    g = (1 / (1 + np.exp(-np.clip(z, -30, 30))) - label) * share
    gh = g[:, None] * w2[:, 0] * (h > 0)
    gx = gh @ w1.T
    d, f = e[0].shape[1], len(e)
    ge = [gx[:, k * d : (k + 1) * d].copy() for k in range(f)]
    for k, (i, j) in enumerate(pairs):
        s = gx[:, f * d + k : f * d + k + 1]
        ge[i] += s * e[j]
        ge[j] += s * e[i]
    return ge, [x.T @ gh, gh.sum(0), h.T @ g[:, None], np.array([g.sum()])]


def score(model: dict, columns: list) -> np.ndarray:
    n = len(columns[0])
    e = [_pooled(t, _flatten(c), n) for t, c in zip(model["tables"], columns, strict=True)]
    return 1 / (1 + np.exp(-np.clip(forward(e, model["dense"])[3], -30, 30)))


#: Samples whose hidden layers are held at once; larger batches go through in parts and step once.
PART = 1 << 15


def train_batch(model: dict, columns: list, label: np.ndarray, weight: np.ndarray, p: ModelParams) -> None:
    """One step in place; rows that occur several times are summed before it."""
    n, total = len(label), weight.sum()
    ge, dense = [], None
    for start in range(0, n, PART):
        at = slice(start, start + PART)
        e = [_pooled(t, _flatten(c[at]), len(label[at])) for t, c in zip(model["tables"], columns, strict=True)]
        own, layers = backward(e, model["dense"], label[at], weight[at] / total)
        ge.append(own)
        dense = layers if dense is None else [x + y for x, y in zip(dense, layers, strict=True)]
    for k, column in enumerate(columns):
        flat, owner, _ = _flatten(column)
        rows, where = np.unique(flat, return_inverse=True)
        grad = ge[0][k] if len(ge) == 1 else np.concatenate([own[k] for own in ge])
        g = scatter_grad(grad[owner] * n, where, len(rows))  # per-sample gradients: the adaptive step divides them out
        acc = model["acc"][k]
        acc[rows] += (g**2).mean(axis=1)
        model["tables"][k][rows] -= p.table_rate * g / np.sqrt(acc[rows] + 1e-8)[:, None]
    dense_step(model, dense, p)


def train(model: dict, columns: list, label: np.ndarray, weight: np.ndarray, p: ModelParams) -> None:
    """Mini-batch training in place."""
    n = len(label)
    if n == 0:
        return
    rng, size = np.random.default_rng(p.seed + 1), p.batch_of(n)
    for _ in range(p.epochs):
        order = rng.permutation(n)
        for start in range(0, n, size):
            at = order[start : start + size]
            train_batch(model, [_rows(c, at) for c in columns], label[at], weight[at], p)
    if p.bits < 32:
        model["tables"] = [quantized(t, p.bits) for t in model["tables"]]


def quantized(table: np.ndarray, bits: int) -> np.ndarray:
    """Entries rounded to the levels of a signed number of so many bits, scaled by the greatest entry."""
    top = np.abs(table).max() if table.size else 0.0
    step = top / (2 ** (bits - 1) - 1)
    return np.round(table / step) * step if step > 0 else table


def dense_step(model: dict, grads: list[np.ndarray], p: ModelParams) -> None:
    if model["moments"] is None:
        model["moments"] = [(np.zeros_like(g), np.zeros_like(g)) for g in grads]
    model["t"] += 1
    t, out = model["t"], []
    for k, g in enumerate(grads):
        m, v = model["moments"][k]
        m, v = 0.9 * m + 0.1 * g, 0.999 * v + 0.001 * g * g
        model["moments"][k] = (m, v)
        update = (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.999**t)) + 1e-6)
        w = model["dense"][k]
        size, move = np.linalg.norm(w), np.linalg.norm(update)
        trust = min(10.0, max(1.0, size / move)) if size > 0 and move > 0 else 1.0
        out.append(w - p.dense_rate * trust * update)
    model["dense"] = out


def auc(label: np.ndarray, value: np.ndarray, weight: np.ndarray | None = None) -> float | None:
    """Exact area under the ROC curve with ties counted half; None if a class is absent."""
    weight = np.ones(len(label)) if weight is None else weight
    _, at = np.unique(value, return_inverse=True)
    pos = np.bincount(at, weight * (label == 1))
    neg = np.bincount(at, weight * (label == 0))
    if pos.sum() == 0 or neg.sum() == 0:
        return None
    below = np.cumsum(neg) - neg
    return float((pos * (below + neg / 2)).sum() / (pos.sum() * neg.sum()))
