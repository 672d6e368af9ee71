"""Line dedup by winnowing over line hashes, with built-in functions only.

The non-blank lines of a text form a sequence of hashes. Grams of ``GRAM`` consecutive lines are
winnowed: of every ``WINDOW`` consecutive grams the one of least hash is selected (the rightmost of
equals), so every repeated run of ``GRAM + WINDOW - 1`` lines or more has a selected gram in common
with its other occurrences. A single line of ``LONG_LINE`` code points or more is selected by
itself. Selected fingerprints carry the hashes of up to ``REACH`` lines on either side. Each
fingerprint's first position in the corpus comes from a pre-aggregated minimum; every later position
is joined with it, the match is extended both ways while lines agree, and the lines of the extended
match are deleted from the later text. A match that agrees on all of its ``REACH`` lines, where no
other match between the same texts goes on, is followed through the texts in rounds until lines
differ. The first occurrence of a line is never deleted.

Winnowing guarantees runs of ``GRAM + WINDOW - 1`` lines and long lines only. With ``every_line`` an
exact pass takes the lines that winnowing and extension leave, single by single: every repeat of a
line that occurs earlier is deleted, whatever its length and neighbours. Winnowing never deletes the
first occurrence of a line, so the exact pass finds it among the lines left.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from idfold.llm.common import ROW_UID, SPACE_CHARS, as_scan, let, join_split, settle, table, with_row_uid

GRAM = 2
WINDOW = 2
#: Lines a fingerprint carries on either side, as winnowing leaves gaps of WINDOW - 1; the rounds behind them double it.
REACH = 3
LONG_LINE = 200


def _lines(text: Column) -> Column:
    return F.split(F.coalesce(text, F.lit("")), "\n")


def _sequence(text: Column) -> Column:
    """Non-blank lines as structs (pos, h, long)."""
    items = F.transform(
        _lines(text),
        lambda x, i: let(F.btrim(x, F.lit(SPACE_CHARS)), lambda t: F.struct(i.alias("pos"), F.xxhash64(t).alias("h"), (F.length(t) >= LONG_LINE).alias("long"), (t == "").alias("blank"))),
    )
    return F.filter(items, lambda e: ~e["blank"])


def _span(n: Column) -> Column:
    """0 .. n - 1, empty for n <= 0."""
    return F.when(n > 0, F.sequence(F.lit(0), n - 1)).otherwise(F.array().cast("array<int>"))


def _selected(seq: Column) -> Column:
    """Structs (key, at, len) of the selected grams and long lines of a sequence."""

    def winnow(grams: Column) -> Column:
        windows = F.greatest(F.size(grams) - (WINDOW - 1), F.least(F.size(grams), F.lit(1)))
        least = lambda i: F.array_min(F.slice(grams, i + 1, F.lit(WINDOW)))
        return F.array_distinct(F.transform(_span(windows), least))

    # (hash, -index): the least struct is the least hash, of equals the rightmost.
    grams = F.transform(
        _span(F.size(seq) - (GRAM - 1)), lambda i: F.struct(F.xxhash64(*[F.get(seq, i + k)["h"] for k in range(GRAM)]).alias("key"), (-i).alias("minus"))
    )
    runs = F.transform(let(grams, winnow), lambda g: F.struct(g["key"].alias("key"), (-g["minus"]).alias("at"), F.lit(GRAM).alias("len")))
    singles = F.filter(
        F.transform(seq, lambda e, i: F.struct(F.when(e["long"], F.xxhash64(e["h"], F.lit("long"))).alias("key"), i.alias("at"), F.lit(1).alias("len"))),
        lambda s: s["key"].isNotNull(),
    )
    return F.concat(runs, singles)


def _plain(seq: Column) -> Column:
    """Lines as structs (pos, h)."""
    return F.transform(seq, lambda e: F.struct(e["pos"].alias("pos"), e["h"].alias("h")))


def _behind(seq: Column, at: Column, way: int, n: int) -> Column:
    """Up to ``n`` lines from the index ``at`` on, forwards (``way`` 1) or backwards (-1), nearest first."""
    if way > 0:
        return F.slice(seq, at + 1, F.lit(n))
    return F.reverse(F.slice(seq, F.greatest(at + 2 - n, F.lit(1)), F.least(F.greatest(at + 1, F.lit(0)), F.lit(n))))


def _anchors(text: Column, *, extend: bool) -> Column:
    """Selected fingerprints with positions inside and, to extend, hashes around, nearest first."""

    def around(seq: Column, s: Column) -> list[Column]:
        before, after = _behind(seq, s["at"] - 1, -1, REACH), _behind(seq, s["at"] + s["len"], 1, REACH)
        return [_plain(before).alias("before"), _plain(after).alias("after")] if extend else []

    def build(seq: Column) -> Column:
        return F.transform(
            _selected(seq),
            lambda s: F.struct(
                s["key"].alias("key"),
                s["at"].alias("at"),
                F.transform(F.slice(seq, s["at"] + 1, s["len"]), lambda e: e["pos"]).alias("inside"),
                *around(seq, s),
            ),
        )

    return let(_sequence(text), build)


def _agreeing(later: Column, first: Column) -> Column:
    """Positions of the leading lines of ``later`` that agree with those of ``first``."""
    start = F.struct(F.array().cast("array<int>").alias("pos"), F.lit(True).alias("open"))

    def step(acc: Column, pair: Column) -> Column:
        same = acc["open"] & F.coalesce(pair["later"]["h"] == pair["first"]["h"], F.lit(False))
        return F.struct(F.when(same, F.concat(acc["pos"], F.array(pair["later"]["pos"]))).otherwise(acc["pos"]).alias("pos"), same.alias("open"))

    pairs = F.zip_with(later, first, lambda x, y: F.struct(x.alias("later"), y.alias("first")))
    return F.aggregate(pairs, start, step, lambda acc: acc["pos"])


def _place(id_col: Column, at: str) -> Column:
    """Where a line is: the order of (doc_id, scan order, line), null doc_ids last."""
    return F.struct(id_col.isNull().alias("n"), id_col.alias("d"), F.col(ROW_UID).alias("u"), F.col(at).alias("at")).alias("where")


def _extended(docs: DataFrame, later: DataFrame, *, text_col: str) -> DataFrame:
    """(row uid, pos): lines of the matches, and of either side as far as they agree with the first occurrence."""
    matches = settle(
        later.select(
            F.col("where.u").alias("u"), F.col("where.at").alias("at"), F.col("f_where.u").alias("f_u"), F.col("f_where.at").alias("f_at"), F.size("inside").alias("len"),
            "inside", *[_agreeing(F.col(c), F.col(f"f_{c}")).alias(c) for c in ("before", "after")],
        )
    )
    # Of matches that follow each other between two texts at one distance, the outermost go on.
    chain = Window.partitionBy("u", "f_u", F.col("at") - F.col("f_at")).orderBy("at", "len")
    apart = {-1: F.col("at") - F.lag(F.col("at") + F.col("len")).over(chain), 1: F.lead("at").over(chain) - F.col("at") - F.col("len")}
    found, fronts, reach = [matches.select("u", F.concat("inside", "before", "after").alias("pos"))], [], REACH
    for way, side in ((-1, "before"), (1, "after")):
        behind = F.lit(-1 - REACH) if way < 0 else F.col("len") + REACH
        full = matches.withColumn("apart", apart[way]).where((F.size(side) == REACH) & (F.col("apart").isNull() | (F.col("apart") > REACH)))
        fronts.append(full.select("u", (F.col("at") + behind).alias("at"), "f_u", (F.col("f_at") + behind).alias("f_at"), F.lit(way).alias("way")))
    front, texts = settle(fronts[0].unionByName(fronts[1])), None
    while front.head(1):
        texts = texts or settle(with_row_uid(docs).select(F.col(ROW_UID).alias("u"), _plain(_sequence(F.col(text_col))).alias("seq")))
        reach *= 2
        ahead = lambda seq, at: F.when(F.col("way") > 0, _behind(seq, at, 1, reach)).otherwise(_behind(seq, at, -1, reach))  # noqa: B023, E731
        own = settle(front.join(texts, "u").select("u", "at", "f_u", "f_at", "way", ahead(F.col("seq"), F.col("at")).alias("own")))
        firsts = settle(own.groupBy("f_u").agg(F.count("*").alias("n")).join(texts.withColumnRenamed("u", "f_u"), "f_u"))
        # A text that very many others repeat meets in no task.
        pairs = join_split(own, firsts, "f_u", count="n")
        step = settle(pairs.select("u", "at", "f_u", "f_at", "way", _agreeing(F.col("own"), ahead(F.col("seq"), F.col("f_at"))).alias("pos")))
        found.append(step.select("u", "pos"))
        front = settle(step.where(F.size("pos") == reach).select("u", (F.col("at") + F.col("way") * reach).alias("at"), "f_u", (F.col("f_at") + F.col("way") * reach).alias("f_at"), "way"))
    return reduce(DataFrame.unionByName, found).select(F.col("u").alias(ROW_UID), "pos")


def _winnowed(docs: DataFrame, *, extend: bool, id_col: str, text_col: str) -> DataFrame:
    """(row uid, removed): lines of selected fingerprints that occur earlier, and of their extensions."""
    around = ["before", "after"] if extend else []
    anchors = settle(
        with_row_uid(docs)
        .select(ROW_UID, F.col(id_col).alias("doc_id"), F.explode(_anchors(F.col(text_col), extend=extend)).alias("a"))
        .select(F.col("a.key").alias("key"), _place(F.col("doc_id"), "a.at"), *[f"a.{c}" for c in ["inside", *around]])
    )
    firsts = settle(
        anchors.groupBy("key")
        .agg(F.min(F.struct("where", *around)).alias("f"), F.count("*").alias("n"))
        .where("n > 1")
        .select("key", "n", *[F.col(f"f.{c}").alias(f"f_{c}") for c in ["where", *around]])
    )
    # A fingerprint that very many documents share meets in no task.
    later = join_split(anchors, firsts, "key", count="n").where("where != f_where")
    if extend:
        gone = _extended(docs, later, text_col=text_col)
    else:
        gone = later.select(F.col("where.u").alias(ROW_UID), F.col("inside").alias("pos"))
    return gone.groupBy(ROW_UID).agg(F.array_sort(F.array_distinct(F.flatten(F.collect_list("pos")))).alias("removed"))


def _rest(docs: DataFrame, runs: DataFrame, *, id_col: str, text_col: str) -> DataFrame:
    """(row uid, removed): of the lines that ``runs`` leaves, those that occur earlier."""
    lines = (
        with_row_uid(docs)
        .select(ROW_UID, F.col(id_col).alias("doc_id"), F.explode(_sequence(F.col(text_col))).alias("e"))
        .select(F.col("e.h").alias("key"), _place(F.col("doc_id"), "e.pos"))
    )
    left = lines.join(runs.select(F.col(ROW_UID).alias("u"), "removed"), F.col("where.u") == F.col("u"), "left")
    left = settle(left.where(F.col("removed").isNull() | ~F.array_contains("removed", F.col("where.at"))).select("key", "where"))
    firsts = settle(left.groupBy("key").agg(F.min("where").alias("f_where"), F.count("*").alias("n")).where("n > 1"))
    # A line that very many documents share meets in no task.
    later = join_split(left, firsts, "key", count="n").where("where != f_where")
    return later.groupBy(F.col("where.u").alias(ROW_UID)).agg(F.array_sort(F.collect_list("where.at")).alias("removed"))


def repeated_lines(docs: DataFrame, *, every_line: bool = False, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(row uid, removed): sorted line numbers, from 0, that repeat earlier runs; rows without any are left out."""
    docs = as_scan(docs)
    runs = _winnowed(docs, extend=True, id_col=id_col, text_col=text_col)
    if not every_line:
        return runs
    runs = settle(runs)
    both = runs.unionByName(_rest(docs, runs, id_col=id_col, text_col=text_col))
    return both.groupBy(ROW_UID).agg(F.array_sort(F.flatten(F.collect_list("removed"))).alias("removed"))


def dedup_lines(docs: DataFrame, *, every_line: bool = False, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per row of ``docs``: doc_id, n_lines, n_removed, removed, text.

    "Later" is the order of (doc_id, scan order, line), null doc_ids last. Lines are compared without
    white space at their ends; blank lines are never counted in runs nor deleted. Null text stays
    null with no lines; empty and repeated texts are ordinary ones (a repeated text loses the runs
    that its first occurrence holds). Extra columns are ignored. ``every_line`` deletes every later
    occurrence of a line: what winnowing selects and extension adds, then by an exact pass what they leave.
    """
    docs = as_scan(docs)
    removed = repeated_lines(docs, every_line=every_line, id_col=id_col, text_col=text_col)
    joined = with_row_uid(docs).select(ROW_UID, F.col(id_col).alias("doc_id"), F.col(text_col).alias("text")).join(removed, ROW_UID, "left")
    none = F.array().cast("array<int>")

    def rest(lines: Column) -> Column:
        stay = F.array_except(_span(F.size(lines)), F.col("removed"))
        return F.array_join(F.transform(stay, lambda i: F.get(lines, i)), "\n")

    return joined.select(
        "doc_id",
        F.when(F.col("text").isNull(), 0).otherwise(F.size(_lines(F.col("text")))).alias("n_lines"),
        F.size(F.coalesce("removed", none)).alias("n_removed"),
        F.coalesce("removed", none).alias("removed"),
        F.when(F.col("removed").isNull(), F.col("text")).otherwise(let(_lines(F.col("text")), rest)).alias("text"),
    )


def op5_winnowed_lines(spark, sf_dir: str) -> DataFrame:
    return dedup_lines(table(spark, sf_dir, "documents"), every_line=True)
