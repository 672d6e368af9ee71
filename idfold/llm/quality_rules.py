"""Quality rules with risk-controlled thresholds, with built-in functions only.

Each rule is a per-mille measure of a text and rejects above a cutoff. Cutoffs come from a fixed
grid, independent of the data. On the labelled holdout the number of good texts that a cutoff would
reject, per stratum, is tested against the allowed rate with the exact binomial tail
(``P(Binomial(n, rate) <= rejected)``, the Clopper-Pearson test). Cutoffs are tested from the laxest
on and testing stops at the first failure (fixed-sequence testing, no correction inside a sequence);
the error level is divided by the number of sequences (rules times strata, Bonferroni), and the
allowed rate by the number of rules, so with confidence ``1 - delta`` no stratum loses more than
``rate`` of its good texts. Among certified cutoffs the laxest of those that reject the most bad
texts net of good ones is taken; where nothing can be certified or gained, the rule is off.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from idfold.llm.common import settle, table
from idfold.llm.text_stats import base_struct, n_upper

#: Cutoffs in per mille, from lax to strict.
GRID = (900, 800, 700, 600, 500, 450, 400, 350, 300, 250, 200, 160, 130, 100, 80, 60, 40, 20)
RULES = ("symbols", "upper", "dup_lines", "repeats")
#: Tails of up to so many terms are summed from the first term, longer ones from the last, the
#: largest, down to where terms no longer show; both give the exact tail.
FORWARD_TERMS = 1_000
#: Strata tables up to this many rows are broadcast; larger ones are joined by shuffle.
BROADCAST_STRATA = 10_000


def measured(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", stratum_col: str = "lang") -> DataFrame:
    """doc_id, stratum, base counts, base_failed and one per-mille measure per rule."""
    narrow = docs.select(
        F.col(id_col).alias("doc_id"),
        F.coalesce(F.col(stratum_col).cast("string"), F.lit("")).alias("stratum"),
        base_struct(F.col(text_col)).alias("s"),
        n_upper(F.col(text_col)).alias("n_upper"),
    ).select("doc_id", "stratum", "s.*", "n_upper")
    per_mille = lambda a, b: (F.lit(1000) * F.col(a) / F.greatest(F.col(b), F.lit(1))).cast("long")
    return narrow.select(
        "*",
        ((F.col("n_words") < 10) | (100 * F.col("n_repeat_words") > 20 * F.col("n_words"))).alias("base_failed"),
        per_mille("n_symbols", "word_chars").alias("symbols"),
        per_mille("n_upper", "word_chars").alias("upper"),
        per_mille("n_dup_lines", "n_lines").alias("dup_lines"),
        per_mille("n_repeat_words", "n_words").alias("repeats"),
    )


def _log_factorial(x: Column) -> Column:
    """ln x! for x over a few hundred, by Stirling's series (error below 1e-18 there)."""
    x = F.greatest(x.cast("double"), F.lit(1.0))
    return x * F.log(x) - x + 0.5 * F.log(2 * math.pi * x) + 1 / (12 * x) - 1 / (360 * x * x * x)


def binomial_tail(k: Column, n: Column, rate: float) -> Column:
    """P(Binomial(n, rate) <= k) term by term in logarithms; 1 where k is at or over the mean.

    From the last term down each term is smaller than the one after it by a factor that only falls,
    so the sum ends where that factor has brought terms below 1e-20 of the largest.
    """
    odds = math.log(rate) - math.log1p(-rate)
    start = F.struct((n * F.lit(math.log1p(-rate))).alias("term"), F.exp(n * F.lit(math.log1p(-rate))).alias("sum"))

    def up(acc: Column, i: Column) -> Column:
        term = acc["term"] + F.log((n - i + 1) / i) + F.lit(odds)
        return F.struct(term.alias("term"), (acc["sum"] + F.exp(term)).alias("sum"))

    none = F.array().cast("array<bigint>")
    steps = F.when(k > 0, F.sequence(F.lit(1).cast("long"), F.least(k, F.lit(FORWARD_TERMS).cast("long")))).otherwise(none)
    short = F.aggregate(steps, start, up, lambda acc: F.least(acc["sum"], F.lit(1.0)))

    last = _log_factorial(n) - _log_factorial(k) - _log_factorial(n - k) + k * F.lit(math.log(rate)) + (n - k) * F.lit(math.log1p(-rate))
    # Terms d below the last are smaller by more than exp(-d * d / (2 n rate)), and by fall ** d.
    fall = -F.log(k * F.lit((1 - rate) / rate) / (n - k + 1))
    reach = F.ceil(F.least(F.sqrt(F.lit(92.0 * rate) * n) + 50, F.lit(46.0) / F.greatest(fall, F.lit(1e-300)) + 1)).cast("long")

    def down(acc: Column, d: Column) -> Column:
        i = k - d + 1  # from term i to term i - 1
        term = acc["term"] + F.log(i / (n - i + 1)) - F.lit(odds)
        return F.struct(term.alias("term"), (acc["sum"] + F.exp(term - last)).alias("sum"))

    back = F.when(k > FORWARD_TERMS, F.sequence(F.lit(1).cast("long"), F.least(k, reach))).otherwise(none)
    long = F.aggregate(back, F.struct(last.alias("term"), F.lit(1.0).alias("sum")), down, lambda acc: F.least(F.exp(last) * acc["sum"], F.lit(1.0)))
    return F.when(n <= 0, F.lit(1.0)).when(k >= n * F.lit(rate), F.lit(1.0)).when(k > FORWARD_TERMS, long).otherwise(short)


def certify(measures: DataFrame, labels: DataFrame, *, rate: float = 0.02, delta: float = 0.05) -> DataFrame:
    """(stratum, rule, cutoff): the chosen cutoffs. ``labels``: doc_id and quality, 1 for good."""
    held = labels.where("doc_id is not null and quality is not null").groupBy("doc_id").agg(F.max("quality").alias("quality"))
    items = F.array(*[F.struct(F.lit(r).alias("rule"), F.col(r).alias("x")) for r in RULES])
    level = F.lit(0)
    for cutoff in GRID:
        level = level + F.when(F.col("i.x") > cutoff, 1).otherwise(0)
    # How many cutoffs of the grid reject the text: counts by (stratum, rule, level) hold all that is needed.
    counts = (
        measures.where("not base_failed")
        .join(held, "doc_id")
        .select("stratum", "quality", F.explode(items).alias("i"))
        .select("stratum", "quality", "i.rule", level.alias("level"))
        .groupBy("stratum", "rule", "level")
        .agg(F.sum(F.when(F.col("quality") == 1, 1).otherwise(0)).alias("good"), F.sum(F.when(F.col("quality") == 0, 1).otherwise(0)).alias("bad"))
    )
    families = counts.agg((F.count_distinct("stratum") * len(RULES)).alias("families"))
    per_rule = counts.groupBy("stratum", "rule").agg(
        F.sum("good").alias("n"), F.collect_list(F.struct("level", "good", "bad")).alias("by_level")
    )
    # A text of level L is rejected by the last L cutoffs, that is by cutoff number c (from 0, lax first)
    # when L > len(GRID) - 1 - c counted from the strict end.
    rejected = lambda what, c: F.aggregate(
        F.filter("by_level", lambda e: e["level"] > (len(GRID) - 1 - c)), F.lit(0).cast("long"), lambda a, e: a + e[what].cast("long")
    )
    tested = (
        per_rule.select("stratum", "rule", "n", "by_level", F.posexplode(F.array(*[F.lit(x) for x in GRID])).alias("c", "cutoff"))
        .select("stratum", "rule", "n", "c", "cutoff", rejected("good", F.col("c")).alias("lost"), rejected("bad", F.col("c")).alias("caught"))
        .withColumn("tail", binomial_tail(F.col("lost"), F.col("n"), rate / len(RULES)))
        .withColumn("failed", (F.col("tail") > F.lit(delta) / families.scalar()).cast("int"))
    )
    so_far = Window.partitionBy("stratum", "rule").orderBy("c").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return (
        tested.withColumn("stopped", F.max("failed").over(so_far))
        .where("stopped = 0 and caught > lost")
        .groupBy("stratum", "rule")
        .agg(F.max(F.struct((F.col("caught") - F.col("lost")).alias("gain"), F.col("cutoff"))).alias("best"))
        .select("stratum", "rule", F.col("best.cutoff").alias("cutoff"))
    )


def judge(docs: DataFrame, labels: DataFrame, *, rate: float = 0.02, delta: float = 0.05, **columns: str) -> DataFrame:
    """One row per text: doc_id, base counts, base_failed, kept, and the measures of the rules.

    Null text has no words and fails the base rule; null strata form one stratum; documents without
    a label are judged but not used for the cutoffs; a doc_id labelled twice counts as good if any
    label is good; repeated rows are judged each; without labels only the base rule acts.
    """
    measures = settle(measured(docs, **columns))
    cutoffs = certify(measures, labels, rate=rate, delta=delta).groupBy("stratum").agg(
        *[F.max(F.when(F.col("rule") == r, F.col("cutoff"))).alias(f"max_{r}") for r in RULES]
    )
    cutoffs = settle(cutoffs)
    if cutoffs.limit(BROADCAST_STRATA + 1).count() <= BROADCAST_STRATA:
        cutoffs = F.broadcast(cutoffs)
    within = F.lit(True)
    for r in RULES:
        within = within & F.coalesce(F.col(r) <= F.col(f"max_{r}"), F.lit(True))
    return measures.join(cutoffs, "stratum", "left").select(
        "doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed",
        (~F.col("base_failed") & within).alias("kept"), "stratum", *RULES,
    )


def op3_risk_controlled_rules(spark, sf_dir: str) -> DataFrame:
    return judge(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")).select(
        "doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept"
    )


def oracle(*, rate: float = 0.02, delta: float = 0.05) -> str:
    """The same judgement as DuckDB SQL; the tail from log-gamma terms."""
    share = rate / len(RULES)
    level = " + ".join(f"(x > {c})::INT" for c in GRID)
    unpivot = " UNION ALL ".join(f"SELECT stratum, quality, '{r}' AS rule, {r} AS x FROM held" for r in RULES)
    cutoffs = ", ".join(f"({k}, {c})" for k, c in enumerate(GRID))
    within = " AND ".join(f"coalesce({r} <= (SELECT cutoff FROM best b WHERE b.stratum = m.stratum AND b.rule = '{r}'), true)" for r in RULES)
    return rf"""WITH d AS MATERIALIZED (SELECT row_number() OVER () AS u, doc_id, coalesce(lang, '') AS stratum, coalesce(text, '') AS t,
  regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS w FROM documents),
wins AS (SELECT u, unnest(range(1, len(w) - 3)) AS i, w FROM d WHERE len(w) > 4),
keyed AS (SELECT u, i, count(*) OVER (PARTITION BY u, array_to_string(w[i:i+4], ' ')) AS n FROM wins),
reps AS (SELECT u, count(DISTINCT p) AS n_repeat_words FROM (SELECT u, unnest([i, i+1, i+2, i+3, i+4]) AS p FROM keyed WHERE n > 1) GROUP BY u),
ls AS (SELECT u, count(*) AS n_lines, count(*) - count(DISTINCT l) AS n_dup_lines FROM (SELECT u, unnest(string_split(t, chr(10))) AS l FROM d) WHERE regexp_matches(l, '[^\x20\x09-\x0D]') GROUP BY u),
base AS (SELECT u, doc_id, stratum, len(w) AS n_words, length(array_to_string(w, '')) AS word_chars, length(t) - length(regexp_replace(t, '[#*$%&|<>]', '', 'g')) AS n_symbols,
  coalesce(n_dup_lines, 0) AS n_dup_lines, coalesce(n_repeat_words, 0) AS n_repeat_words, coalesce(n_lines, 0) AS n_lines, length(t) - length(regexp_replace(t, '\p{{Lu}}+', '', 'g')) AS n_upper
  FROM d LEFT JOIN reps USING (u) LEFT JOIN ls USING (u)),
m AS MATERIALIZED (SELECT *, n_words < 10 OR 100 * n_repeat_words > 20 * n_words AS base_failed, 1000 * n_symbols // greatest(word_chars, 1) AS symbols, 1000 * n_upper // greatest(word_chars, 1) AS upper,
  1000 * n_dup_lines // greatest(n_lines, 1) AS dup_lines, 1000 * n_repeat_words // greatest(n_words, 1) AS repeats FROM base),
held AS (SELECT m.*, quality FROM m JOIN (SELECT doc_id, max(quality) AS quality FROM labels WHERE quality IS NOT NULL GROUP BY 1) USING (doc_id) WHERE NOT base_failed),
lv AS (SELECT stratum, rule, quality, {level} AS level FROM ({unpivot})),
cut(c, cutoff) AS (VALUES {cutoffs}),
tested AS (SELECT stratum, rule, c, cutoff, count(*) FILTER (quality = 1) AS n, count(*) FILTER (quality = 1 AND level > {len(GRID) - 1} - c) AS lost, count(*) FILTER (quality = 0 AND level > {len(GRID) - 1} - c) AS caught FROM lv, cut GROUP BY ALL),
tails AS (SELECT *, CASE WHEN n = 0 OR lost >= n * {share} THEN 1.0 ELSE
  (SELECT sum(exp(lgamma(n + 1) - lgamma(i + 1) - lgamma(n - i + 1) + i * ln({share}) + (n - i) * ln(1 - {share}))) FROM (SELECT unnest(range(lost + 1)) AS i)) END AS tail FROM tested),
stops AS (SELECT *, max((tail > {delta} / ({len(RULES)} * (SELECT count(DISTINCT stratum) FROM lv)))::INT) OVER (PARTITION BY stratum, rule ORDER BY c) AS stopped FROM tails),
best AS (SELECT stratum, rule, arg_max(cutoff, (caught - lost, cutoff)) AS cutoff FROM stops WHERE stopped = 0 AND caught > lost GROUP BY ALL)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, NOT base_failed AND {within} AS kept FROM m"""
