"""Agglomeration of one chain held in arrays: the local engine's inner loop.

A chain is a sequence of clusters sorted by value. A link joins neighbours; a round selects links
through gates, joins those that touch into runs, and merges every run. Order is kept by merging
neighbours only, so a chain is sorted once.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, replace

import numpy as np

GATES = ("rarity", "gap", "bulk")


@dataclass(frozen=True)
class FoldParams:
    """Parameters of agglomeration.

    row_budget: clusters wanted. stride: merges per round (None: 1 % of the start, at least 1).
    size_cap: most ids of a cluster (None: 4 times the mean at the budget). gates: which filters, in
    order. widths: how many links leave the first, second and last place, as multiples of the merges
    still to do; fewer gates use the last of them. value_rule: mean, count_weighted or size_weighted.
    split: pairs (alternate links of an over-cap run) or pack (greedy left to right up to the cap).
    bulk_limit: stride (never more than the merges to do) or all (every fitting survivor).
    strict: sizes must stay below the cap rather than at most equal it. micro: whole-number values.
    """

    row_budget: int
    stride: int | None = None
    size_cap: int | None = None
    gates: tuple[str, ...] = GATES
    widths: tuple[float, ...] = (2.0, 1.5, 1.0)
    value_rule: str = "mean"
    split: str = "pairs"
    bulk_limit: str = "stride"
    strict: bool = False
    micro: bool = False
    max_rounds: int | None = None

    def resolved(self, n: int) -> FoldParams:
        budget = max(self.row_budget, 1)
        return replace(
            self,
            row_budget=budget,
            stride=self.stride or max(1, math.ceil(n / 100)),
            size_cap=self.size_cap or max(1, math.ceil(4 * n / budget)),
        )

    def place_widths(self, r: int) -> list[int]:
        """Links that may leave each active gate when ``r`` merges are to be done."""
        multiples = self.widths[-len(self.gates) :] if self.gates else ()
        return [max(1, math.floor(m * r)) for m in multiples]


#: Ways to use access counts: gates and value rule.
FREQUENCY_MODES = {
    "none": {"gates": ("gap", "bulk"), "value_rule": "mean"},
    "weight_only": {"gates": ("gap", "bulk"), "value_rule": "count_weighted"},
    "weight_and_filter": {"gates": ("rarity", "gap", "bulk"), "value_rule": "count_weighted"},
    "filter_only": {"gates": ("rarity", "gap", "bulk"), "value_rule": "mean"},
}


@dataclass
class Chain:
    value: np.ndarray
    size: np.ndarray
    count: np.ndarray

    def __len__(self) -> int:
        return len(self.value)


def norm_counts(count: np.ndarray) -> np.ndarray:
    """1 + count / L2 norm over the current clusters; 1 where all counts are zero."""
    norm = math.sqrt(float(np.sum(count.astype(np.float64) ** 2)))
    return 1 + count / norm if norm > 0 else np.ones(len(count))


def link_scores(chain: Chain) -> dict[str, np.ndarray]:
    q = norm_counts(chain.count)
    return {"rarity": q[:-1] * q[1:], "gap": np.diff(chain.value), "bulk": chain.size[:-1] + chain.size[1:]}


def select_links(chain: Chain, r: int, p: FoldParams) -> tuple[np.ndarray, dict]:
    """Indices of the links that pass all gates, ascending, and what happened on the way."""
    scores = link_scores(chain)
    alive = np.arange(len(chain) - 1)  # in the order of the last gate's rank
    told = {"links": len(alive), "kept": [], "fallback": False}
    for place, (gate, width) in enumerate(zip(p.gates, p.place_widths(r), strict=True)):
        last = place == len(p.gates) - 1
        if gate == "bulk":
            bulk = scores["bulk"][alive]
            fits = bulk < p.size_cap if p.strict else bulk <= p.size_cap
            if fits.any():
                alive = alive[fits]
                alive = alive[:width] if last and p.bulk_limit == "stride" else alive
            else:
                told["fallback"] = True
                alive = alive[np.argsort(bulk, kind="stable")[:width]]
        else:
            alive = alive[np.argsort(scores[gate][alive], kind="stable")[:width]]
        told["kept"].append(len(alive))
    if not p.gates:
        alive = alive[:r]
    return np.sort(alive), told


def runs_of(links: np.ndarray) -> list[np.ndarray]:
    """Maximal sequences of consecutive links."""
    return np.split(links, np.flatnonzero(np.diff(links) > 1) + 1) if len(links) else []


def split_runs(links: np.ndarray, size: np.ndarray, p: FoldParams) -> tuple[np.ndarray, int]:
    """Thin out runs whose merged size is over the cap; links that stay and number of runs split."""
    kept, n_split = [], 0
    for run in runs_of(links):
        total = int(size[run[0] : run[-1] + 2].sum())
        over = total >= p.size_cap if p.strict else total > p.size_cap
        if not over:
            kept.append(run)
            continue
        n_split += 1
        if p.split == "pairs":
            kept.append(run[::2])
        else:
            held, stay = int(size[run[0]]), []
            for link in run:
                grown = held + int(size[link + 1])
                if grown < p.size_cap or (not p.strict and grown == p.size_cap):
                    stay.append(link)
                    held = grown
                else:
                    held = int(size[link + 1])
            kept.append(np.array(stay or run[:1], dtype=links.dtype))
    return (np.concatenate(kept) if kept else links), n_split


def merge(chain: Chain, links: np.ndarray, p: FoldParams) -> tuple[Chain, np.ndarray]:
    """The shorter chain, and for each old cluster the index of its new one."""
    joined = np.zeros(len(chain), dtype=np.int64)
    joined[links + 1] = 1
    to = np.arange(len(chain)) - np.cumsum(joined)
    n = int(to[-1]) + 1
    members = np.bincount(to, minlength=n)
    size = np.bincount(to, chain.size, n).astype(np.int64)
    count = np.bincount(to, chain.count, n).astype(np.int64)
    weights = {"mean": None, "count_weighted": chain.count, "size_weighted": chain.size}[p.value_rule]
    if p.micro:
        value = np.zeros(n, dtype=np.int64)
        total = members.astype(np.int64) if weights is None else np.zeros(n, dtype=np.int64)
        plain, weighted = np.zeros(n, dtype=np.int64), np.zeros(n, dtype=np.int64)
        np.add.at(plain, to, chain.value)
        if weights is not None:
            np.add.at(weighted, to, chain.value * weights)
            np.add.at(total, to, weights)
        use = total > 0 if weights is not None else np.zeros(n, dtype=bool)
        top, below = np.where(use, weighted, plain), np.where(use, total, members)
        value = (2 * top + below) // (2 * below)
        value = np.where(members == 1, plain, value)
    else:
        plain = np.bincount(to, chain.value, n) / members
        if weights is None:
            value = plain
        else:
            total = np.bincount(to, weights, n)
            value = np.where(total > 0, np.bincount(to, chain.value * weights, n) / np.where(total > 0, total, 1), plain)
        # Rounding must not carry a mean out of its members, which would break the order.
        first = np.searchsorted(to, np.arange(n))
        value = np.clip(value, chain.value[first], chain.value[first + members - 1])
    return Chain(value, size, count), to


def fold_round(chain: Chain, p: FoldParams) -> tuple[Chain, np.ndarray, dict] | None:
    """One round; None when the budget is met."""
    n = len(chain)
    r = min(p.stride, n - p.row_budget)
    if r <= 0 or n < 2:
        return None
    links, told = select_links(chain, r, p)
    n_split = 0
    if "bulk" in p.gates and not told["fallback"]:
        links, n_split = split_runs(links, chain.size, p)
    after, to = merge(chain, links, p)
    kept = told["kept"] + [0, 0]
    return after, to, {"n": n, "r": r, "links": told["links"], "kept1": kept[0], "kept2": kept[1], "fallback": told["fallback"], "selected": len(links), "runs_split": n_split, "merges": n - len(after)}


def fold_arrays(value: np.ndarray, count: np.ndarray, params: FoldParams) -> tuple[np.ndarray, Chain, list[dict]]:
    """Fold singletons sorted by (value, id): row of every id, the final clusters, the trace."""
    n = len(value)
    p = params.resolved(n)
    chain = Chain(np.asarray(value, dtype=np.int64 if p.micro else np.float64), np.ones(n, dtype=np.int64), np.asarray(count, dtype=np.int64))
    row, trace = np.arange(n), []
    if n and not p.micro and np.isnan(chain.value).any():
        raise ValueError("a latent value is null or NaN")
    while p.max_rounds is None or len(trace) < p.max_rounds:
        done = fold_round(chain, p)
        if done is None:
            break
        chain, to, told = done
        row = to[row]
        trace.append({"round": len(trace) + 1, **told})
    return row, chain, trace
