"""Per-text statistics from built-in functions; one row in, one row out, no shuffle."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from idfold.llm.common import let, words_of

#: The characters that count as symbols, as a Java pattern.
SYMBOL_PATTERN = r"[#*$%&|<>]"


def word_chars(words: Column) -> Column:
    return F.aggregate(words, F.lit(0).cast("long"), lambda n, w: n + F.length(w).cast("long"))


def n_symbols(text: Column) -> Column:
    text = F.coalesce(text, F.lit(""))
    return (F.length(text) - F.length(F.regexp_replace(text, SYMBOL_PATTERN, ""))).cast("long")


def n_upper(text: Column) -> Column:
    text = F.coalesce(text, F.lit(""))
    return (F.length(text) - F.length(F.regexp_replace(text, r"\p{Lu}+", ""))).cast("long")


def worded_lines(text: Column) -> Column:
    """Lines, split at newlines, that hold a word."""
    return F.filter(F.split(F.coalesce(text, F.lit("")), "\n"), lambda x: F.rlike(x, F.lit(r"[^\x20\x09-\x0D]")))


def n_dup_lines(lines: Column) -> Column:
    """Lines equal to an earlier one."""
    return (F.size(lines) - F.size(F.array_distinct(lines))).cast("long")


def _covered(hashes: Column, width: int) -> Column:
    """Words in windows whose hash occurs twice or more; ``hashes`` has one entry per window."""
    pairs = F.sort_array(F.transform(hashes, lambda h, i: F.struct(h.alias("h"), i.alias("i"))))

    def twins(s: Column) -> Column:
        def twin(e: Column, k: Column) -> Column:
            before, after = F.get(s, k - 1)["h"], F.get(s, k + 1)["h"]
            return F.when(F.coalesce(before == e["h"], F.lit(False)) | F.coalesce(after == e["h"], F.lit(False)), e["i"])

        return F.sort_array(F.filter(F.transform(s, twin), lambda p: p.isNotNull()))

    start = F.struct(F.lit(0).alias("n"), F.lit(-width).alias("at"))

    def step(acc: Column, p: Column) -> Column:
        return F.struct((acc["n"] + F.least(F.lit(width), p - acc["at"])).alias("n"), p.alias("at"))

    return F.aggregate(let(pairs, twins), start, step, lambda acc: acc["n"].cast("long"))


def n_repeat_words(words: Column, width: int = 5) -> Column:
    """Words inside ``width``-word windows that occur twice or more in the text.

    Windows are compared by 64-bit hashes. Texts without a repeated window, nearly all, leave after
    one hash-set pass; only the others are sorted.
    """

    def windows(h: Column) -> Column:
        spots = F.sequence(F.lit(0), F.size(h) - F.lit(width))
        return F.transform(spots, lambda i: F.xxhash64(*[F.get(h, i + k) for k in range(width)]))

    none = F.lit(0).cast("long")

    def count(g: Column) -> Column:
        return F.when(F.size(F.array_distinct(g)) == F.size(g), none).otherwise(_covered(g, width))

    return let(words, lambda w: F.when(F.size(w) <= width, none).otherwise(let(F.transform(w, lambda x: F.xxhash64(x)), lambda h: let(windows(h), count))))


def base_struct(text: Column) -> Column:
    """The five base counts and the number of lines of a text as one struct."""

    def build(w: Column) -> Column:
        return let(
            worded_lines(text),
            lambda lines: F.struct(
                F.size(w).cast("long").alias("n_words"),
                word_chars(w).alias("word_chars"),
                n_symbols(text).alias("n_symbols"),
                n_dup_lines(lines).alias("n_dup_lines"),
                n_repeat_words(w).alias("n_repeat_words"),
                F.size(lines).cast("long").alias("n_lines"),
            ),
        )

    return let(words_of(text), build)
