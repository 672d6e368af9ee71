"""Training from a file of samples: the same as in memory for small sets, every sample once an epoch for large ones."""

from __future__ import annotations

import numpy as np
import pytest

from idfold.operators import sample_file, student


def held(x, y, w):
    out = sample_file.SampleFile(x.shape[1])
    for k in range(0, len(y), 97):
        out.add(x[k : k + 97], y[k : k + 97], w[k : k + 97])
    return out


def drawn(n=3000):
    rng = np.random.default_rng(4)
    x = rng.integers(0, 20, (n, 2))
    return x, (x[:, 0] % 2 ^ (rng.random(n) < 0.2)).astype(int), rng.integers(1, 4, n)


def columns(s):
    return [s["x"][:, [0]].astype(np.int64), s["x"][:, [1]].astype(np.int64)]


def test_small_sets_train_as_in_memory():
    x, y, w = drawn()
    p, order = student.ModelParams(epochs=3), np.lexsort([w, y, *x.T])
    models = [student.init_model([20, 20], p) for _ in range(2)]
    student.train(models[0], [x[order][:, [0]], x[order][:, [1]]], y[order], w[order].astype(float), p)
    sample_file.fit(models[1], held(x, y, w), p, columns=columns, order=lambda s: np.lexsort([s["w"], s["y"], *s["x"].T]))
    assert all(np.array_equal(a, b) for a, b in zip(models[0]["tables"], models[1]["tables"], strict=True))


def test_large_sets_train_in_blocks(monkeypatch):
    monkeypatch.setattr(sample_file, "BLOCK", 500)
    x, y, w = drawn()
    p, seen, real = student.ModelParams(epochs=4), [], sample_file.train_batch
    monkeypatch.setattr(sample_file, "train_batch", lambda m, c, label, weight, q: (seen.append((len(label), weight.sum())), real(m, c, label, weight, q)))
    model, samples = student.init_model([20, 20], p), held(x, y, w)
    sample_file.fit(model, samples, p, columns=columns, order=None)
    assert sum(n for n, _ in seen) == 4 * len(y) and sum(s for _, s in seen) == 4 * w.sum() and max(n for n, _ in seen) <= 500
    monkeypatch.setattr(sample_file, "CHUNK", 700)
    assert student.auc(sample_file.fields(samples, "y"), sample_file.scores(model, samples, columns=columns)) > 0.7


def test_batches_in_parts_take_the_same_step(monkeypatch):
    x, y, w = drawn(300)
    models = [student.init_model([20, 20], student.ModelParams()) for _ in range(2)]
    for model, part in zip(models, (1 << 15, 64), strict=True):
        monkeypatch.setattr(student, "PART", part)
        student.train_batch(model, [x[:, [0]], x[:, [1]]], y, w.astype(float), student.ModelParams())
    assert all(np.allclose(a, b, rtol=1e-9) for a, b in zip(models[0]["tables"], models[1]["tables"], strict=True))


def test_ids_beyond_32_bits_are_refused():
    with pytest.raises(ValueError):
        sample_file.SampleFile(1).add(np.array([[1 << 31]]), np.array([0]))
