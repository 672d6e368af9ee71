"""Quality classifier from weak labels.

Heuristic labellers vote good, bad or abstain on every text. Expectation-maximisation over the
counts of vote patterns (all documents counted; a few thousand patterns at most) estimates each
labeller's accuracy per class and the share of good texts, without any gold label. The posterior of
a text's pattern is its soft label. A linear scorer on hashed words, word endings and coarse text
shape is trained on a bounded sample of soft-labelled texts and scores every text.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from idfold.llm.common import ROW_UID, as_scan, let, settle, table, with_row_uid, words_of
from idfold.llm.text_stats import n_symbols, n_upper, word_chars

#: Bound on the distinct texts the scorer is trained on: those of least hash, whatever the corpus size.
TRAIN_TEXTS = 4096
#: Slots of the hashed weight table; the last SHAPES slots are kept for the shape features.
SLOTS = 1 << 14
SHAPES = 64
LABELLERS = ("symbols", "noise", "plain", "capitals", "bangs", "pipes", "variety", "stutter")
#: A plain word, letters with one mark at most behind them, between white space.
PLAIN_WORD = r"(?<![^\x20\x09-\x0D])[\p{L}'’-]++[.,;:?!]?(?![^\x20\x09-\x0D])"

GOOD, BAD, ABSTAIN = 1, 0, -1


def _vote(bad: Column, good: Column) -> Column:
    return F.when(bad, BAD).when(good, GOOD).otherwise(ABSTAIN).cast("int")


def _stutters(words: Column) -> Column:
    """Words equal to the word before them."""
    same = F.zip_with(words, F.slice(words, F.lit(2), F.greatest(F.size(words), F.lit(1))), lambda x, y: x == y)
    return F.size(F.filter(same, lambda e: e)).cast("long")


def measures(text: Column) -> Column:
    """Counts that labellers and shape features use, as one struct per text (n_plain: characters of plain words)."""
    text = F.coalesce(text, F.lit(""))
    return let(
        words_of(text),
        lambda w: F.struct(
            F.size(w).cast("long").alias("n_words"),
            F.size(F.array_distinct(w)).cast("long").alias("n_distinct"),
            F.greatest(word_chars(w), F.lit(1).cast("long")).alias("n_chars"),
            n_symbols(text).alias("n_symbols"),
            n_upper(text).alias("n_upper"),
            (F.length(text) - F.length(F.replace(text, F.lit("|"), F.lit("")))).cast("long").alias("n_pipes"),
            (F.length(text) - F.length(F.replace(text, F.lit("!"), F.lit("")))).cast("long").alias("n_bangs"),
            (F.length(text) - F.length(F.regexp_replace(text, PLAIN_WORD, ""))).cast("long").alias("n_plain"),
            _stutters(w).alias("n_stutters"),
        ),
    )


def votes(m: Column) -> list[Column]:
    """One vote per labeller from the struct of ``measures``.

    Every kind of junk concerns two labellers or more: their agreement is what EM learns from.
    """
    n, chars = m["n_words"], m["n_chars"]
    noise = m["n_symbols"] + m["n_bangs"]
    variety = m["n_distinct"] / F.sqrt(F.greatest(n, F.lit(1)).cast("double"))
    return [
        _vote(20 * (m["n_symbols"] - m["n_pipes"]) > chars, 100 * (m["n_symbols"] - m["n_pipes"]) <= chars),
        _vote(25 * noise > chars, 100 * noise <= chars),
        _vote((n >= 15) & (10 * m["n_plain"] < 7 * chars), 10 * m["n_plain"] > 9 * chars),
        _vote((n >= 5) & (10 * m["n_upper"] > 3 * chars), 10 * m["n_upper"] < chars),
        _vote((n >= 5) & (5 * m["n_bangs"] > n), 20 * m["n_bangs"] < n),
        _vote((n >= 10) & (4 * m["n_pipes"] > n), m["n_pipes"] == 0),
        _vote((n >= 30) & (variety < 2), variety > 3),
        _vote((n >= 10) & (5 * m["n_stutters"] > n), 50 * m["n_stutters"] < n),
    ]


def fit_labellers(patterns: list[tuple[tuple[int, ...], int]], *, rounds: int = 100) -> tuple[dict[tuple[int, ...], float], np.ndarray, float]:
    """EM over (votes, count): posterior of good per pattern, accuracy[labeller, class], share of good.

    Each labeller knows one kind of junk, so texts start as bad where any labeller objects; that also
    fixes which class is the good one. Abstentions carry no evidence. Counts are smoothed by one
    vote either way.
    """
    if not patterns:
        return {}, np.full((len(LABELLERS), 2), 0.5), 0.5
    v = np.array([p for p, _ in patterns], dtype=np.int64)
    n = np.array([c for _, c in patterns], dtype=np.float64)
    q = np.where((v == BAD).any(1), 0.1, np.where((v == GOOD).any(1), 0.9, 0.5))
    for _ in range(rounds):
        share = float(np.clip((n * q).sum() / n.sum(), 1e-6, 1 - 1e-6))
        right_good = ((n * q) @ (v == GOOD) + 1) / ((n * q) @ (v != ABSTAIN) + 2)
        right_bad = ((n * (1 - q)) @ (v == BAD) + 1) / ((n * (1 - q)) @ (v != ABSTAIN) + 2)
        for_good = np.where(v == GOOD, np.log(right_good), np.where(v == BAD, np.log1p(-right_good), 0.0)).sum(1)
        for_bad = np.where(v == BAD, np.log(right_bad), np.where(v == GOOD, np.log1p(-right_bad), 0.0)).sum(1)
        gap = np.clip(np.log(share) - np.log1p(-share) + for_good - for_bad, -30, 30)
        after = 1 / (1 + np.exp(-gap))
        if np.abs(after - q).max() < 1e-9:
            break
        q = after
    return {p: float(x) for (p, _), x in zip(patterns, q, strict=True)}, np.stack([right_bad, right_good], 1), share


def shape_slots(m: Column) -> Column:
    """Slots of the shape features: coarse levels of variety, symbols, capitals, plain words and stutter."""
    n, chars = F.greatest(m["n_words"], F.lit(1)), m["n_chars"]
    level = lambda x, top: F.least(F.greatest(F.floor(x), F.lit(0)), F.lit(top)).cast("int")
    base = SLOTS - SHAPES
    return F.array(
        F.lit(base) + level(m["n_distinct"] * F.sqrt(n.cast("double")) / n, 15),
        F.lit(base + 16) + level(40 * m["n_symbols"] / chars, 15),
        F.lit(base + 32) + level(20 * m["n_upper"] / chars, 15),
        F.lit(base + 48) + level(8 * (m["n_plain"] + 30) / (chars + 30), 7),
        F.lit(base + 56) + level(10 * m["n_stutters"] / n, 7),
    )


def word_slots(w: Column) -> Column:
    """The two slots of a word: its own and that of its last two characters."""
    room = F.lit(SLOTS - SHAPES)
    return F.array(F.pmod(F.xxhash64(w), room).cast("int"), F.pmod(F.xxhash64(F.right(w, F.lit(2)), F.lit(1)), room).cast("int"))


def train_scorer(rows: np.ndarray, slots: np.ndarray, values: np.ndarray, soft: np.ndarray, *, rounds: int = 150, rate: float = 0.5, decay: float = 1e-5) -> np.ndarray:
    """Logistic regression on soft labels by Adam over the whole sample; weights with the bias last."""
    weights, first, second = np.zeros(SLOTS + 1), np.zeros(SLOTS + 1), np.zeros(SLOTS + 1)
    n = len(soft)
    for t in range(1, rounds + 1):
        z = np.bincount(rows, values * weights[slots], n) + weights[-1]
        error = (1 / (1 + np.exp(-np.clip(z, -30, 30))) - soft) / max(n, 1)
        g = np.append(np.bincount(slots, values * error[rows], SLOTS), error.sum()) + decay * weights
        first, second = 0.9 * first + 0.1 * g, 0.999 * second + 0.001 * g * g
        weights -= rate * (first / (1 - 0.9**t)) / (np.sqrt(second / (1 - 0.999**t)) + 1e-8)
    return weights


def _score(text: Column, weights: np.ndarray) -> Column:
    """bias + mean word weight + shape weights, folded over the words of the text inside the JVM."""
    held = F.split(F.lit(",".join(f"{x:.6g}" for x in weights)), ",").cast("array<double>")  # folded to one constant
    at = lambda i: F.get(held, i)
    room = F.lit(SLOTS - SHAPES)

    def total(w: Column) -> Column:
        return F.aggregate(
            w, F.lit(0.0), lambda s, x: s + at(F.pmod(F.xxhash64(x), room).cast("int")) + at(F.pmod(F.xxhash64(F.right(x, F.lit(2)), F.lit(1)), room).cast("int"))
        )

    words = let(words_of(text), lambda w: total(w) / F.greatest(F.size(w), F.lit(1)))
    shapes = F.aggregate(let(measures(text), shape_slots), F.lit(0.0), lambda s, i: s + at(i))
    return F.lit(float(weights[-1])) + words + shapes


def fit(docs: DataFrame, *, text_col: str = "text", train_texts: int = TRAIN_TEXTS) -> np.ndarray:
    """Weights of the scorer: votes of all texts, EM over their patterns, training on the sample."""
    docs = as_scan(docs)
    text = F.coalesce(F.col(text_col), F.lit(""))
    voted = settle(
        with_row_uid(docs.select(text_col)).select(ROW_UID, F.xxhash64(text, F.lit("sample")).alias("order"), let(measures(text), lambda m: F.array(*votes(m))).alias("votes"))
    )
    patterns = [(tuple(r["votes"]), r["n"]) for r in voted.groupBy("votes").agg(F.count("*").alias("n")).orderBy("votes").collect()]  # 3^labellers at most
    good, _, _ = fit_labellers(patterns)
    # One row of each distinct text, so that a text copied a million times takes one place.
    texts = voted.groupBy("order").agg(F.min(F.struct(ROW_UID, "votes")).alias("first"))
    chosen = settle(texts.orderBy("order").limit(train_texts).select("first.*"))
    soft = {r[ROW_UID]: good[tuple(r["votes"])] for r in chosen.collect()}  # train_texts rows at most
    sample = with_row_uid(docs.select(text_col)).join(F.broadcast(chosen.select(ROW_UID)), ROW_UID)

    def slots(w: Column) -> Column:
        both = F.concat(F.flatten(F.transform(w, word_slots)), let(measures(text), shape_slots))
        return F.transform(both, lambda slot: F.struct(slot.alias("slot"), F.size(w).alias("n_words")))

    # Per text at most SLOTS distinct slots come to the driver.
    counted = (
        sample.select(ROW_UID, F.explode(let(words_of(text), slots)).alias("s"))
        .select(ROW_UID, "s.*")
        .groupBy(ROW_UID, "n_words", "slot")
        .agg(F.count("*").alias("n"))
        .toArrow()
    )
    rows = np.searchsorted(np.array(sorted(soft), dtype=np.int64), counted.column(ROW_UID).to_numpy())
    slot = counted.column("slot").to_numpy().astype(np.int64)
    length = np.maximum(counted.column("n_words").to_numpy(), 1)
    values = np.where(slot < SLOTS - SHAPES, counted.column("n").to_numpy() / length, 1.0)
    del counted
    pa.default_memory_pool().release_unused()
    return train_scorer(rows, slot, values, np.array([soft[u] for u in sorted(soft)]))


def classify(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", train_texts: int = TRAIN_TEXTS) -> DataFrame:
    """doc_id, score (log-odds of good) and kept (score >= 0) for every row of ``docs``.

    Null and blank texts have no words: only bias and shape count. Nothing is dropped here; repeated
    rows score alike; an empty table gives an empty result; extra columns are ignored.
    """
    weights = fit(docs, text_col=text_col, train_texts=train_texts)
    return docs.select(F.col(id_col).alias("doc_id"), _score(F.col(text_col), weights).alias("score")).select("doc_id", "score", (F.col("score") >= 0).alias("kept"))


def keep_good(docs: DataFrame, *, text_col: str = "text", train_texts: int = TRAIN_TEXTS) -> DataFrame:
    """The rows of ``docs`` that the scorer does not reject, with all their columns.

    Nulls, repeats and empty tables as in ``classify``: a null text is judged like a blank one, of
    repeated rows all stay or none, an empty table stays empty.
    """
    docs = as_scan(docs)
    return docs.where(_score(F.col(text_col), fit(docs, text_col=text_col, train_texts=train_texts)) >= 0)


def op2_weak_label_classifier(spark, sf_dir: str) -> DataFrame:
    return classify(table(spark, sf_dir, "documents"))
