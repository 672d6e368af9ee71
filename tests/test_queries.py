"""Every query with an oracle against DuckDB at the smallest scale; the others must run."""

from __future__ import annotations

import pytest

from idfold import catalog
from tests.conftest import SF

QUERIES, ORACLES = catalog.load()
SLOW = {n for n in QUERIES if n.startswith("wl_fig")} | {"wl_tuning", "fold_gate_orders", "teach_als", "teach_fm"}


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_against_duckdb(spark, duck, same, name):
    same(QUERIES[name](spark, SF).toPandas(), duck.execute(ORACLES[name]).df())


@pytest.mark.parametrize("name", sorted(set(QUERIES) - set(ORACLES) - SLOW))
def test_runs(spark, name):
    assert QUERIES[name](spark, SF).count() > 0


def test_one_experiment(spark):
    got = {r["cell"]: r for r in QUERIES["wl_fig3"](spark, SF).collect()}
    assert got["learned_10"]["reps"] == 2 and 0 <= got["learned_10"]["mean_auc"] <= 1


def test_library_does_not_need_llm():
    import re
    from pathlib import Path

    root = Path(__file__).resolve().parents[1] / "idfold"
    for f in root.rglob("*.py"):
        if "llm" not in f.relative_to(root).parts:
            assert not re.search(r"idfold\.llm|from \.llm|import llm", f.read_text()), f


def test_grid_comes_from_tables(spark):
    assert {f.rsplit("/", 1)[1] for f in QUERIES["join_cross_grid"](spark, SF).inputFiles()} == {"orders.parquet", "lineitem.parquet", "customer.parquet"}
