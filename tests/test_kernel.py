"""Worked rounds, invariants and brute force for the folding kernel."""

from __future__ import annotations

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from idfold.operators.kernel import FREQUENCY_MODES, Chain, FoldParams, fold_arrays, fold_round, runs_of, split_runs


def clusters(values, counts=None, rounds=None, **params):
    counts = counts or [1] * len(values)
    p = FoldParams(**params)
    row, chain, trace = fold_arrays(np.array(values, float), np.array(counts), FoldParams(**{**p.__dict__, "max_rounds": rounds}))
    return [(round(v, 3), int(z), int(c)) for v, z, c in zip(chain.value, chain.size, chain.count, strict=True)], row, trace


GAP = {"gates": ("gap", "bulk")}


def test_two_separate_merges_in_one_round():
    got, row, trace = clusters([0, 10, 100, 110, 500], stride=2, row_budget=3, size_cap=2, **GAP)
    assert got == [(5, 2, 2), (105, 2, 2), (500, 1, 1)]
    assert row.tolist() == [0, 0, 1, 1, 2] and len(trace) == 1


def test_touching_links_become_one_cluster():
    got, *_ = clusters([0, 10, 20, 30, 500], stride=2, row_budget=3, size_cap=99, **GAP)
    assert got == [(10, 3, 3), (30, 1, 1), (500, 1, 1)]


def test_all_fitting_survivors_overshoot_the_budget():
    got, *_ = clusters([0, 10, 20, 30, 500], stride=2, row_budget=3, size_cap=99, bulk_limit="all", **GAP)
    assert got == [(15, 4, 4), (500, 1, 1)]


def test_pairs_then_fallback():
    args = dict(stride=4, row_budget=1, size_cap=2)
    got, _, trace = clusters([0, 10, 20, 30, 40], rounds=1, **args)
    assert got == [(5, 2, 2), (25, 2, 2), (40, 1, 1)] and trace[0]["runs_split"] == 1
    got, _, trace = clusters([0, 10, 20, 30, 40], **args)
    assert got == [(23.333, 5, 5)] and trace[1]["fallback"]


def test_triple_over_the_cap_keeps_its_left_link():
    got, *_ = clusters([0, 10, 25, 45], rounds=1, stride=2, row_budget=2, size_cap=2, **GAP)
    assert got == [(5, 2, 2), (25, 1, 1), (45, 1, 1)]


def test_rare_neighbours_merge_first():
    got, *_ = clusters([0, 10, 20, 30], [1000, 1, 1, 1000], stride=1, row_budget=3, size_cap=2)
    assert got == [(0, 1, 1000), (15, 2, 2), (30, 1, 1000)]


def test_value_rules():
    assert clusters([0, 10], [9, 1], stride=1, row_budget=1, size_cap=2)[0] == [(5, 2, 10)]
    assert clusters([0, 10], [9, 1], stride=1, row_budget=1, size_cap=2, value_rule="count_weighted")[0] == [(1, 2, 10)]
    assert clusters([0, 10], [0, 0], stride=1, row_budget=1, size_cap=2, value_rule="count_weighted")[0] == [(5, 2, 0)]


def test_plain_means_depend_on_the_order_of_merging():
    one = clusters([0, 10, 40], stride=2, row_budget=1, size_cap=9, **GAP)[0]
    two = clusters([0, 10, 40], stride=1, row_budget=1, size_cap=9, **GAP)[0]
    assert one[0][0] == 16.667 and two[0][0] == 22.5
    weighted = {"value_rule": "count_weighted", **GAP}
    assert clusters([0, 10, 40], stride=2, row_budget=1, size_cap=9, **weighted)[0] == clusters([0, 10, 40], stride=1, row_budget=1, size_cap=9, **weighted)[0]


@pytest.mark.parametrize("values,budget", [([], 1), ([3.0], 1), ([1.0, 2.0], 2), ([1.0, 2.0], 5)])
def test_nothing_to_do(values, budget):
    got, row, trace = clusters(values, row_budget=budget)
    assert len(got) == len(values) and not trace and row.tolist() == list(range(len(values)))


def test_edge_cases_end():
    assert clusters([7.0] * 6, row_budget=2, stride=1, size_cap=1)[0][0][0] == 7
    assert len(clusters([1.0, 2.0, 3.0], [0, 0, 0], row_budget=1, stride=99, size_cap=3)[0]) == 1
    with pytest.raises(ValueError):
        clusters([1.0, float("nan")], row_budget=1)


def test_pack_fills_up_to_the_cap():
    p = FoldParams(row_budget=1, size_cap=3, split="pack", stride=9)
    stay, n = split_runs(np.arange(6), np.ones(7, dtype=np.int64), p)
    assert stay.tolist() == [0, 1, 3, 4] and n == 1


def test_runs():
    assert [r.tolist() for r in runs_of(np.array([1, 2, 5, 7, 8, 9]))] == [[1, 2], [5], [7, 8, 9]]
    assert runs_of(np.array([], dtype=int)) == []


chains = st.lists(st.tuples(st.integers(0, 50), st.integers(0, 9)), min_size=1, max_size=40)


@settings(max_examples=60, deadline=None)
@given(chains, st.integers(1, 40), st.integers(1, 10), st.integers(1, 9), st.sampled_from(sorted(FREQUENCY_MODES)), st.sampled_from(["pairs", "pack"]))
def test_invariants(items, budget, stride, cap, mode, split):
    items = sorted(items)
    values, counts = np.array([v for v, _ in items], float), np.array([c for _, c in items])
    p = FoldParams(row_budget=budget, stride=stride, size_cap=cap, split=split, **FREQUENCY_MODES[mode])
    row, chain, trace = fold_arrays(values, counts, p)
    assert len(chain) == min(len(items), max(budget, 1))
    assert chain.size.sum() == len(items) and chain.count.sum() == counts.sum()
    assert (np.diff(chain.value) >= 0).all() and (np.diff(row) >= 0).all() and set(row) == set(range(len(chain)))
    assert all(t["merges"] >= 1 and t["kept1"] <= max(2 * t["r"], t["links"]) for t in trace)
    for k in range(len(chain)):
        inside = values[row == k]
        assert inside.min() - 1e-9 <= chain.value[k] <= inside.max() + 1e-9


@settings(max_examples=40, deadline=None)
@given(chains, st.integers(1, 10))
def test_scaling_values_leaves_the_map_unchanged(items, budget):
    items = sorted(items)
    values, counts = np.array([v for v, _ in items], float), np.array([c for _, c in items])
    p = FoldParams(row_budget=budget, stride=2, size_cap=5)
    assert (fold_arrays(values, counts, p)[0] == fold_arrays(values * 4, counts, p)[0]).all()


@settings(max_examples=40, deadline=None)
@given(st.lists(st.integers(0, 1000), min_size=2, max_size=25), st.integers(1, 25))
def test_single_merges_equal_nearest_pair_greedy(values, budget):
    values = sorted(values)
    groups = [[float(v)] for v in values]
    centre = [float(v) for v in values]
    while len(groups) > budget:
        gaps = [centre[i + 1] - centre[i] for i in range(len(centre) - 1)]
        i = gaps.index(min(gaps))
        groups[i : i + 2] = [groups[i] + groups[i + 1]]
        centre[i : i + 2] = [(centre[i] + centre[i + 1]) / 2]
    row, _, _ = fold_arrays(np.array(values, float), np.ones(len(values)), FoldParams(row_budget=budget, stride=1, gates=("gap",)))
    assert [int((row == k).sum()) for k in range(len(groups))] == [len(g) for g in groups]


def test_round_is_none_at_the_budget():
    c = Chain(np.array([1.0, 2.0]), np.ones(2, dtype=int), np.ones(2, dtype=int))
    assert fold_round(c, FoldParams(row_budget=2, stride=1, size_cap=2)) is None
