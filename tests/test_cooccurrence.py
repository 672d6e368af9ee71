"""Co-occurrence counts every sample, large ones too."""

from __future__ import annotations

from collections import Counter
from itertools import combinations
from math import log

from idfold.operators import baselines


def test_large_bags_count(spark):
    bags = {0: range(80), 1: range(0, 80, 2), 2: range(0, 80, 4), 3: [0, 4, 90], 4: [90, 91]}
    got = {(r["a"], r["b"]): r for r in baselines.cooccurrence(spark.createDataFrame([(s, i) for s, b in bags.items() for i in b], "sample_id long, id long")).collect()}
    single, pairs = Counter(i for b in bags.values() for i in b), Counter(p for b in bags.values() for p in combinations(b, 2))
    want = {p: n for p, n in pairs.items() if n >= 3}
    assert {p: r["together"] for p, r in got.items()} == want and want
    assert all(abs(r["pmi"] - log(want[p] * 5 / (single[p[0]] * single[p[1]]))) < 1e-5 for p, r in got.items())
