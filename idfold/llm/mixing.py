"""Mixing sources to target weights by iterative proportional fitting, with built-in functions only.

Documents are counted into cells of (source, language, topic). Raking scales the token weights of
the cells to the target shares of each margin in turn, under the bound that no cell weighs more than
the tokens it holds: a cell's weight is the lesser of its tokens and a product of one factor per
margin value. The ratio of weight to tokens is the probability with which the cell's documents are
drawn, so the expected sample is the raked one and nothing is clipped afterwards; the draw is a hash
of the doc_id, the same on every run and every cluster.

A target beyond what a margin value holds at the budget cannot be met: such a value is taken whole
and the rest of its margin rises in proportion. ``margins`` reports targets, feasible and expected
shares and what is left between them.

No document moves. Cell tables up to ``FOLD_CELLS`` rows are raked in one fold over the rounds, in one
row; larger ones by windows over the cell table, one exchange of it a margin and round. Both give the
same weights. The driver gets one row per margin and step of the feasible shares, nothing else.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from idfold.llm.common import let, settle, table, unit_draw, words_of

MARGINS = ("source", "lang", "topic")
#: Target shares are proportional to (tokens of the margin) ** exponent unless given.
EXPONENTS = {"source": 0.5, "lang": 0.7, "topic": 0.7}
#: Rounds of raking; ``margins`` shows how far the shares are from their goals after them.
ROUNDS = 24
#: Cell tables up to this many rows are raked in one row.
FOLD_CELLS = 1 << 14
#: Share of all tokens that the sample should hold.
BUDGET = 0.8
#: Cell tables up to this many rows are broadcast to the documents; larger ones are joined by shuffle.
BROADCAST_CELLS = 100_000
#: Probabilities are rounded to this many decimals, so that the order of sums cannot show.
DECIMALS = 6


def topic_of(text: Column, n_words: Column) -> Column:
    """A coarse topic from the surface of a text: data, list, dialogue, long or prose."""
    text = F.coalesce(text, F.lit(""))
    lines = F.length(text) - F.length(F.replace(text, F.lit("\n"), F.lit(""))) + 1
    digits = F.length(text) - F.length(F.regexp_replace(text, "[0-9]+", ""))
    asks = F.length(text) - F.length(F.replace(text, F.lit("?"), F.lit("")))
    return (
        F.when(20 * digits > F.length(text), "data")
        .when((lines >= 3) & (n_words < 8 * lines), "list")
        .when(50 * asks > n_words, "dialogue")
        .when(n_words >= 1000, "long")
        .otherwise("prose")
    )


def counted(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", lang_col: str = "lang") -> DataFrame:
    """doc_id, source, lang, topic, n_tokens; null source or language counts as empty text."""
    n = F.size(words_of(F.col(text_col))).cast("long")
    return docs.select(
        F.col(id_col).alias("doc_id"),
        F.coalesce(F.col(source_col).cast("string"), F.lit("")).alias("source"),
        F.coalesce(F.col(lang_col).cast("string"), F.lit("")).alias("lang"),
        n.alias("n_tokens"),
        F.col(text_col).alias("t"),
    ).select("doc_id", "source", "lang", topic_of(F.col("t"), F.col("n_tokens")).alias("topic"), "n_tokens")


def _wanted(cells: DataFrame, targets: dict[str, DataFrame] | None) -> DataFrame:
    """(margin, value, held, share): the values that occur, their tokens and target shares."""
    parts = []
    for m in MARGINS:
        held = cells.groupBy(F.col(m).alias("value")).agg(F.sum("tokens").cast("double").alias("held"))
        if targets and m in targets:
            given = targets[m].toDF("value", "share").select("value", F.col("share").cast("double").alias("raw"))
            found = held.join(given, "value", "left").withColumn("raw", F.when(F.col("held") > 0, F.coalesce("raw", F.lit(0.0))).otherwise(0.0))
        else:
            found = held.withColumn("raw", F.pow("held", F.lit(EXPONENTS[m])))
        parts.append(found.select(F.lit(m).alias("margin"), "value", "held", "raw"))
    every = settle(parts[0].unionByName(parts[1]).unionByName(parts[2]))
    sums = {r["margin"]: r["s"] for r in every.groupBy("margin").agg(F.sum("raw").alias("s")).collect()}  # three rows
    share = F.lit(0.0)
    for m in MARGINS:
        share = F.when(F.col("margin") == m, F.col("raw") / F.lit(float(sums.get(m) or 1.0))).otherwise(share)
    return every.select("margin", "value", "held", share.alias("share"))


def _feasible(wanted: DataFrame, want: float) -> DataFrame:
    """``wanted`` with goal: the share, none above held / want; what is cut goes to the others in proportion."""
    most = F.col("held") / F.lit(want)
    scales = {m: 1.0 for m in MARGINS}

    def scaled() -> Column:
        out = F.lit(0.0)
        for m in MARGINS:
            out = F.when(F.col("margin") == m, F.col("share") * F.lit(scales[m])).otherwise(out)
        return out

    while True:
        full = (scaled() >= most) & (F.col("share") > 0)
        rows = (
            wanted.groupBy("margin")
            .agg(F.sum(F.when(full, most).otherwise(0.0)).alias("cut"), F.sum(F.when(full, 0.0).otherwise(F.col("share"))).alias("free"))
            .collect()
        )  # three rows
        after = {r["margin"]: max(scales[r["margin"]], (1 - r["cut"]) / r["free"]) if r["free"] > 1e-12 else scales[r["margin"]] for r in rows}
        if all(after[m] <= scales[m] * (1 + 1e-12) for m in after):
            return wanted.withColumn("goal", F.least(scaled(), most))
        scales.update(after)


def _fit(now: DataFrame, margin: str, want: float) -> DataFrame:
    """One margin fitted: cells at their bound stay there while a value has to grow, the others share what is missing."""
    same = Window.partitionBy(margin)
    tokens, free, over = F.col("tokens"), F.col("free_weight"), F.col("free_weight") >= F.col("tokens")
    goal = F.col(f"goal_{margin}") * F.lit(want)
    held, now_held = F.sum(tokens).over(same), F.sum(F.least(tokens, free)).over(same)
    bound, loose = F.sum(F.when(over, tokens).otherwise(0.0)).over(same), F.sum(F.when(over, 0.0).otherwise(free)).over(same)
    grow = F.when(loose > 0, F.greatest((goal - bound) / loose, F.lit(1.0))).otherwise(1.0)
    shrink = F.when(now_held > 0, goal / now_held).otherwise(0.0)
    whole = goal >= held * F.lit(1 - 1e-12)
    after = F.when(whole, F.greatest(free, tokens)).when(goal >= now_held, free * grow).otherwise(free * shrink)
    return now.withColumn("free_weight", after)


def _by_windows(now: DataFrame, want: float, rounds: int) -> DataFrame:
    """``now`` (margins, tokens, free_weight, goals) after all rounds, written out after each."""
    for _ in range(rounds):
        for m in MARGINS:
            now = _fit(now, m, want)
        now = settle(now)
    return now


def _by_fold(now: DataFrame, want: float, rounds: int) -> DataFrame:
    """The same in one row: an aggregate over the rounds, whose state is the array of free weights."""
    cells = settle(now.select(*MARGINS, "tokens", "free_weight", *[f"goal_{m}" for m in MARGINS], (F.row_number().over(Window.orderBy(*MARGINS)) - 1).alias("i")))
    row = cells.agg(F.sort_array(F.collect_list(F.struct("i", "tokens", "free_weight"))).alias("cells"))
    for m in MARGINS:
        values = cells.groupBy(m).agg(F.first(f"goal_{m}").alias("goal"), F.sum("tokens").alias("held"), F.sort_array(F.collect_list("i")).alias("members"))
        row = row.withColumn(f"values_{m}", values.agg(F.sort_array(F.collect_list(F.struct(F.col(m), "goal", "held", "members")))).scalar())
    # The number of a cell's value in its margin, cell by cell.
    for m in MARGINS:
        pairs = F.flatten(F.transform(f"values_{m}", lambda v, k: F.transform(v["members"], lambda i: F.struct(i.alias("i"), k.alias("k")))))
        row = row.withColumn(f"code_{m}", F.transform(F.sort_array(pairs), lambda p: p["k"]))
    row = row.withColumn("tokens", F.transform("cells", lambda c: c["tokens"]))
    token = lambda i: F.get(F.col("tokens"), i)

    def fit(weights: Column, m: str) -> Column:
        def factor(v: Column) -> Column:
            start = F.struct(*[F.lit(0.0).alias(x) for x in ("held", "bound", "loose")])

            def add(acc: Column, i: Column) -> Column:
                x, over = F.get(weights, i), F.get(weights, i) >= token(i)
                return F.struct(
                    (acc["held"] + F.least(token(i), x)).alias("held"),
                    (acc["bound"] + F.when(over, token(i)).otherwise(0.0)).alias("bound"),
                    (acc["loose"] + F.when(over, 0.0).otherwise(x)).alias("loose"),
                )

            goal = v["goal"] * F.lit(want)

            def scale(acc: Column) -> Column:
                grow = F.when(acc["loose"] > 0, F.greatest((goal - acc["bound"]) / acc["loose"], F.lit(1.0))).otherwise(1.0)
                shrink = F.when(acc["held"] > 0, goal / acc["held"]).otherwise(0.0)
                return F.when(goal >= v["held"] * F.lit(1 - 1e-12), F.lit(-1.0)).when(goal >= acc["held"], grow).otherwise(shrink)

            return F.aggregate(v["members"], start, add, scale)

        def apply(factors: Column) -> Column:
            # A factor of -1 stands for a value that is taken whole.
            def one(x: Column, i: Column) -> Column:
                f = F.get(factors, F.get(F.col(f"code_{m}"), i))
                return F.when(f < 0, F.greatest(x, token(i))).otherwise(x * f)

            return F.transform(weights, one)

        return let(F.transform(f"values_{m}", factor), apply)

    def one_round(weights: Column, _: Column) -> Column:
        return let(fit(weights, "source"), lambda w: let(fit(w, "lang"), lambda x: fit(x, "topic")))

    weights = F.aggregate(F.sequence(F.lit(1), F.lit(rounds)), F.transform("cells", lambda c: c["free_weight"]), one_round)
    raked = row.select(F.posexplode(weights).alias("i", "after"))
    return cells.join(raked, "i").select(*MARGINS, "tokens", F.col("after").alias("free_weight"))


def rake(cells: DataFrame, *, targets: dict[str, DataFrame] | None = None, budget: float = BUDGET, rounds: int = ROUNDS, fold_cells: int = FOLD_CELLS) -> tuple[DataFrame, DataFrame]:
    """(cells with weight and probability, margin values with share and goal).

    ``cells``: source, lang, topic and tokens, as a scan. Weights sum to ``budget`` times all tokens
    where the targets leave room for that. Cells of a value without a target get weight zero; cells
    without tokens take the budget itself as probability.
    """
    size = cells.agg(F.sum("tokens").alias("n"), F.count("*").alias("cells")).first()
    want = budget * float(size["n"] or 0)
    goals = settle(_feasible(_wanted(cells, targets), want or 1.0))
    now = cells.select(*MARGINS, F.col("tokens").cast("double").alias("tokens"), (F.col("tokens") * F.lit(budget)).cast("double").alias("free_weight"))
    for m in MARGINS:
        now = now.join(goals.where(F.col("margin") == m).select(F.col("value").alias(m), F.col("goal").alias(f"goal_{m}")), m)
    if want and rounds > 0:
        now = _by_fold(now, want, rounds) if size["cells"] <= fold_cells else _by_windows(settle(now), want, rounds)
    weight = F.least("tokens", "free_weight")
    chance = F.round(F.when(F.col("tokens") > 0, weight / F.col("tokens")).otherwise(F.lit(budget)), DECIMALS)
    return now.select(*MARGINS, "tokens", weight.alias("weight"), chance.alias("probability")), goals


def _raked(rows: DataFrame, targets: dict[str, DataFrame] | None, budget: float, rounds: int) -> tuple[DataFrame, DataFrame]:
    return rake(settle(rows.groupBy(*MARGINS).agg(F.sum("n_tokens").alias("tokens"))), targets=targets, budget=budget, rounds=rounds)


def margins(docs: DataFrame, *, targets: dict[str, DataFrame] | None = None, budget: float = BUDGET, rounds: int = ROUNDS, **columns: str) -> DataFrame:
    """margin, value, target, feasible (target under the bound), expected and residual share (expected less feasible)."""
    cells, goals = _raked(counted(docs, **columns), targets, budget, rounds)
    total = cells.agg(F.sum("weight")).first()[0] or 1.0
    parts = [cells.groupBy(F.lit(m).alias("margin"), F.col(m).alias("value")).agg((F.sum("weight") / F.lit(float(total))).alias("expected")) for m in MARGINS]
    expected = parts[0].unionByName(parts[1]).unionByName(parts[2])
    return goals.join(expected, ["margin", "value"]).select(
        "margin", "value", F.col("share").alias("target"), F.col("goal").alias("feasible"), "expected", (F.col("expected") - F.col("goal")).alias("residual")
    )


def is_small(chances: DataFrame) -> bool:
    return chances.limit(BROADCAST_CELLS + 1).count() <= BROADCAST_CELLS


def _draw(id_: Column) -> Column:
    return unit_draw(F.coalesce(id_.cast("string"), F.lit("null")), F.lit("mix"))


def mix(docs: DataFrame, *, targets: dict[str, DataFrame] | None = None, budget: float = BUDGET, rounds: int = ROUNDS, **columns: str) -> DataFrame:
    """One row per row of ``docs``: doc_id, source, lang, topic, n_tokens, probability, kept.

    ``targets`` maps margins to tables of two columns, value and share; margins left out are
    tempered. Repeated rows of one doc_id share one draw; null doc_ids share the draw of ``null``;
    an empty table gives an empty result; extra columns are ignored.
    """
    rows = settle(counted(docs, **columns))
    chances = settle(_raked(rows, targets, budget, rounds)[0].select(*MARGINS, "probability"))
    joined = rows.join(F.broadcast(chances) if is_small(chances) else chances, list(MARGINS))
    return joined.select("doc_id", *MARGINS, "n_tokens", "probability", (_draw(F.col("doc_id")) < F.col("probability")).alias("kept"))


def sample(docs: DataFrame, *, targets: dict[str, DataFrame] | None = None, budget: float = BUDGET, rounds: int = ROUNDS, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", lang_col: str = "lang") -> DataFrame:
    """The drawn rows of ``docs`` with all their columns, whatever their names.

    A row's cell follows from the row itself, so texts are not moved: the probabilities come to them.
    Nulls, repeats and empty tables as in ``mix``.
    """
    columns = {"id_col": id_col, "text_col": text_col, "source_col": source_col, "lang_col": lang_col}
    chances = settle(_raked(counted(docs, **columns), targets, budget, rounds)[0].select(*MARGINS, "probability"))
    text = F.col(f"`{text_col}`")
    cell = F.struct(
        F.coalesce(F.col(f"`{source_col}`").cast("string"), F.lit("")).alias("source"),
        F.coalesce(F.col(f"`{lang_col}`").cast("string"), F.lit("")).alias("lang"),
        let(F.size(words_of(text)).cast("long"), lambda n: topic_of(text, n)).alias("topic"),
    )
    known = chances.select(F.struct(*MARGINS).alias("cell"), "probability")
    # All columns travel in one struct, so that none can clash with the names used here.
    whole = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), cell.alias("cell"), _draw(F.col(f"`{id_col}`")).alias("draw"))
    joined = whole.join(F.broadcast(known) if is_small(chances) else known, "cell")
    return joined.where(F.col("draw") < F.col("probability")).select(*[F.col("row").getField(c).alias(c) for c in docs.columns])


def op4_raked_mixing(spark, sf_dir: str) -> DataFrame:
    return mix(table(spark, sf_dir, "documents"))


#: Steps of the feasible shares that the SQL form unrolls; Spark goes on until nothing changes.
SQL_STEPS = 8


def oracle(docs: str = "documents", *, budget: float = BUDGET, rounds: int = ROUNDS) -> str:
    """The same computation as one chain of DuckDB common table expressions."""
    n = r"len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+'))"
    parts = [
        f"n0 AS (SELECT doc_id, coalesce(source, '') AS source, coalesce(lang, '') AS lang, coalesce(text, '') AS t, {n}::BIGINT AS n_tokens FROM {docs})",
        """counted AS (SELECT doc_id, source, lang, n_tokens,
            CASE WHEN 20 * (length(t) - length(regexp_replace(t, '[0-9]+', '', 'g'))) > length(t) THEN 'data'
                 WHEN length(t) - length(replace(t, chr(10), '')) + 1 >= 3 AND n_tokens < 8 * (length(t) - length(replace(t, chr(10), '')) + 1) THEN 'list'
                 WHEN 50 * (length(t) - length(replace(t, '?', ''))) > n_tokens THEN 'dialogue'
                 WHEN n_tokens >= 1000 THEN 'long' ELSE 'prose' END AS topic FROM n0)""",
        "cells AS MATERIALIZED (SELECT source, lang, topic, sum(n_tokens)::DOUBLE AS tokens FROM counted GROUP BY ALL)",
        f"total AS MATERIALIZED (SELECT {budget} * sum(tokens) AS want FROM cells)",
    ]
    for m in MARGINS:
        parts.append(f"p_{m} AS (SELECT {m}, sum(tokens) AS held, pow(sum(tokens), {EXPONENTS[m]}) AS raw FROM cells GROUP BY {m})")
        parts.append(f"v_{m} AS MATERIALIZED (SELECT {m}, held / nullif(want, 0) AS most, raw / nullif(sum(raw) OVER (), 0) AS share FROM p_{m}, total)")
        parts.append(f"f_{m}_0 AS (SELECT 1.0::DOUBLE AS scale)")
        for k in range(SQL_STEPS):
            full = "share * scale >= most AND share > 0"
            parts.append(
                f"f_{m}_{k + 1} AS MATERIALIZED (SELECT greatest(any_value(scale), coalesce((1 - sum(CASE WHEN {full} THEN most ELSE 0 END))"
                f" / nullif(sum(CASE WHEN {full} THEN 0 ELSE share END), 0), 0)) AS scale FROM v_{m}, f_{m}_{k})"
            )
        parts.append(f"g_{m} AS MATERIALIZED (SELECT {m}, least(share * scale, most) AS goal_{m} FROM v_{m}, f_{m}_{SQL_STEPS})")
    parts.append(f"w AS MATERIALIZED (SELECT source, lang, topic, tokens, tokens * {budget} AS u, goal_source, goal_lang, goal_topic FROM cells JOIN g_source USING (source) JOIN g_lang USING (lang) JOIN g_topic USING (topic))")
    last = "w"
    for r in range(rounds):
        for m in MARGINS:
            now = f"w{r}_{m}"
            parts.append(
                f"{now} AS MATERIALIZED (SELECT source, lang, topic, tokens, goal_source, goal_lang, goal_topic,"
                f" CASE WHEN goal >= held * (1 - 1e-12) THEN greatest(u, tokens) WHEN goal >= now_held THEN u * CASE WHEN loose > 0 THEN greatest((goal - bound) / loose, 1.0) ELSE 1.0 END"
                f" ELSE u * CASE WHEN now_held > 0 THEN goal / now_held ELSE 0 END END AS u"
                f" FROM (SELECT *, goal_{m} * want AS goal, sum(tokens) OVER s AS held, sum(least(tokens, u)) OVER s AS now_held,"
                f" sum(CASE WHEN u >= tokens THEN tokens ELSE 0 END) OVER s AS bound, sum(CASE WHEN u >= tokens THEN 0 ELSE u END) OVER s AS loose FROM {last}, total WINDOW s AS (PARTITION BY {m})))"
            )
            last = now
    parts.append(f"chances AS (SELECT source, lang, topic, round(CASE WHEN tokens > 0 THEN least(tokens, u) / tokens ELSE {budget} END, {DECIMALS}) AS probability FROM {last})")
    draw = "(('0x' || substr(md5(coalesce(doc_id::VARCHAR, 'null') || ':mix'), 1, 12))::BIGINT + 0.5) / 281474976710656.0"
    return f"WITH {', '.join(parts)} SELECT doc_id, source, lang, topic, n_tokens, probability, {draw} < probability AS kept FROM counted JOIN chances USING (source, lang, topic)"
