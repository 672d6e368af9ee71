"""Exact dedup with a heavy-hitter split.

Equal texts share the SHA-256 of their normalised form. A Misra-Gries pass over the digests finds
those frequent enough to make a hot shuffle key; their winners are verified exactly and broadcast,
so the rows of hot groups are resolved on the map side. All other digests go through an ordinary
hash shuffle, where no group exceeds a ``1 / counters`` share of the rows.
"""

from __future__ import annotations

from collections import Counter

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from idfold.llm.common import ROW_UID, SPACE_CHARS, as_scan, settle, with_row_uid

#: Counters of the Misra-Gries summary; also the bound on the rows that are broadcast.
COUNTERS = 1024


def digests(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(row uid, doc_id, points, digest): SHA-256 of the text without white space; null is empty."""
    text = F.coalesce(F.col(text_col), F.lit(""))
    return with_row_uid(as_scan(docs)).select(
        ROW_UID,
        F.col(id_col).alias("doc_id"),
        F.length(text).cast("long").alias("points"),
        F.sha2(F.translate(text, SPACE_CHARS, "").cast("binary"), 256).alias("digest"),
    )


def misra_gries(counts: Counter, more: Counter, counters: int) -> Counter:
    """Merge two summaries, keeping at most ``counters`` entries.

    Every key whose true count exceeds ``total / (counters + 1)`` survives any sequence of merges.
    """
    merged = counts + more
    if len(merged) <= counters:
        return merged
    cut = sorted(merged.values(), reverse=True)[counters]
    return Counter({key: n - cut for key, n in merged.items() if n > cut})


def frequent_digests(keyed: DataFrame, *, counters: int = COUNTERS) -> DataFrame:
    """At most ``counters`` digests, all those held by over ``1 / (counters + 1)`` of the rows among them."""

    def summarise(batches):
        summary: Counter = Counter()
        for batch in batches:
            summary = misra_gries(summary, Counter(batch["digest"].value_counts().to_dict()), counters)
        yield pd.DataFrame({"digest": list(summary), "n": list(summary.values())}).astype({"digest": str, "n": "int64"})

    partial = keyed.select("digest").mapInPandas(summarise, "digest string, n long")
    return partial.groupBy("digest").agg(F.sum("n").alias("n")).orderBy(F.desc("n"), "digest").limit(counters)


def exact_dedup(
    docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", counters: int = COUNTERS
) -> DataFrame:
    """One row per input row: doc_id, keep_id, group_size, kept, text_sha256 and the row's uid.

    Of equal texts the row with the most code points stays, then the smallest doc_id (null last),
    then the first in scan order, so repeated rows keep exactly one. Null text counts as empty; an
    empty table gives an empty result; other columns of ``docs`` are ignored.
    """
    keyed = settle(digests(docs, id_col=id_col, text_col=text_col))
    rank = F.struct(
        (-F.col("points")).alias("a"), F.col("doc_id").isNull().alias("b"), F.col("doc_id").alias("c"), F.col(ROW_UID).alias("d")
    )
    candidates = F.broadcast(settle(frequent_digests(keyed, counters=counters)).select("digest"))
    hot = (
        keyed.join(candidates, "digest", "left_semi")
        .groupBy("digest")
        .agg(F.min(rank).alias("best"), F.count("*").alias("group_size"))
        .where("group_size > 1")
    )
    winners = F.broadcast(settle(hot))  # at most ``counters`` rows
    marked = keyed.join(winners, "digest", "left")
    done = marked.where("best is not null").select(
        "doc_id", F.col("best.c").alias("keep_id"), "group_size", (F.col("best.d") == F.col(ROW_UID)).alias("kept"), "digest", ROW_UID
    )
    by_digest = Window.partitionBy("digest")
    first = by_digest.orderBy(F.desc("points"), F.asc_nulls_last("doc_id"), ROW_UID)
    rest = marked.where("best is null").select(
        "doc_id",
        F.first("doc_id").over(first).alias("keep_id"),
        F.count("*").over(by_digest).alias("group_size"),
        (F.row_number().over(first) == 1).alias("kept"),
        "digest",
        ROW_UID,
    )
    return done.unionByName(rest).withColumnRenamed("digest", "text_sha256")


def keep_winners(docs: DataFrame, **options) -> DataFrame:
    """The rows of ``docs`` that stay, with all their columns.

    As ``exact_dedup``: null text is empty, of repeated rows one stays, an empty table stays empty.
    A column named ROW_UID raises.
    """
    docs = as_scan(docs)
    kept = exact_dedup(docs, **options).where("kept").select(ROW_UID)
    return with_row_uid(docs).join(kept, ROW_UID, "left_semi").drop(ROW_UID)


def op7_exact_dedup(spark, sf_dir: str) -> DataFrame:
    from idfold.llm.common import table

    return exact_dedup(table(spark, sf_dir, "documents")).select("doc_id", "keep_id", "group_size", "kept", "text_sha256")


SQL = r"""
WITH keyed AS (
  SELECT doc_id, length(coalesce(text, '')) AS points,
         sha256(regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]', '', 'g')) AS text_sha256
  FROM documents)
SELECT doc_id,
       first_value(doc_id) OVER w AS keep_id,
       count(*) OVER (PARTITION BY text_sha256) AS group_size,
       row_number() OVER w = 1 AS kept,
       text_sha256
FROM keyed
WINDOW w AS (PARTITION BY text_sha256 ORDER BY points DESC, doc_id NULLS LAST)
"""
