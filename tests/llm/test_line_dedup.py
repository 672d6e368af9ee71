"""op5 deletes every later occurrence of a line, alone or in a run of two."""

from __future__ import annotations

import random

from pyspark.sql import functions as F

from idfold.llm import line_dedup


def test_no_repeat_of_a_line_stays(spark, tmp_path):
    rng = random.Random(6)
    pool = [f"short line {i}" for i in range(30)] + ["wide " * 60, "", "  ", "}"]
    texts = [rng.choice([None, ""]) if rng.random() < 0.1 else "\n".join(rng.choice(["", " "]) + rng.choice([*pool, f"own {d}"]) for _ in range(rng.randrange(1, 9))) for d in range(80)]
    texts[:2] = ["own a\nshort line 1\nown b", "own c\nshort line 1\nown d"]
    (tmp_path / "sf").mkdir()
    spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").write.parquet(f"{tmp_path}/sf/documents.parquet")
    got = {r["doc_id"]: r for r in line_dedup.op5_winnowed_lines(spark, f"{tmp_path}/sf").collect()}
    seen = set()
    for d, t in enumerate(texts):
        want = []
        for i, x in enumerate((t or "").split("\n")):
            x = x.strip(" \t\n\x0b\x0c\r")
            if x and x in seen:
                want.append(i)
            seen.add(x)
        assert got[d]["removed"] == want, d
        assert got[d]["text"] == (None if t is None else "\n".join(x for i, x in enumerate(t.split("\n")) if i not in want))


def test_winnowing_takes_runs_and_the_exact_pass_only_the_rest(spark, tmp_path):
    run = [f"line {i} of a run" for i in range(4)]
    texts = ["\n".join(["a", *run, "alone"]), "\n".join(["b", *run]), "alone\nc"]
    spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").coalesce(1).write.parquet(f"{tmp_path}/d")
    docs, by = spark.read.parquet(f"{tmp_path}/d"), {"id_col": "doc_id", "text_col": "text"}
    runs = line_dedup._winnowed(docs, extend=False, **by)
    removed = lambda df: {r["__row_uid"]: set(r["removed"]) for r in df.collect()}
    won, rest = removed(runs), removed(line_dedup._rest(docs, runs, **by))
    assert len(won[1]) >= 2 and won[1] | rest.get(1, set()) == {1, 2, 3, 4} and not won[1] & rest.get(1, set())
    assert rest[2] == {0} and 2 not in won


def test_matches_extend_as_far_as_lines_agree(spark, tmp_path, monkeypatch):
    """Of a run only one fingerprint is selected: the lines around it go by extension, before any exact pass."""
    one = lambda seq: F.filter(real(seq), lambda s: s["at"] == 20)
    real = line_dedup._selected
    monkeypatch.setattr(line_dedup, "_selected", one)
    run = [f"line {i} of a run" for i in range(60)]
    other = [*run[:5], "x", *run[6:44], "y", *run[45:]]
    run[19:23] = other[19:23] = ["wide " * 60] * 4  # the fingerprint at 20 is a long line
    (tmp_path / "sf").mkdir()
    spark.createDataFrame([(0, "\n".join(run)), (1, "\n".join(other))], "doc_id long, text string").coalesce(1).write.parquet(f"{tmp_path}/sf/documents.parquet")
    docs = spark.read.parquet(f"{tmp_path}/sf/documents.parquet")
    called, passes = line_dedup._rest, []
    monkeypatch.setattr(line_dedup, "_rest", lambda docs, runs, **by: (passes.append({r["__row_uid"]: r["removed"] for r in runs.collect()}), called(docs, runs, **by))[1])
    got = {r["doc_id"]: r["removed"] for r in line_dedup.dedup_lines(docs, every_line=True).collect()}
    assert passes[0][1] == list(range(6, 44))
    assert got[1] == [i for i in range(60) if i not in (5, 44)] and got[0] == [20, 21, 22]
