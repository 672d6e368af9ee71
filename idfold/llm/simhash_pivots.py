"""SimHash near-dedup with pivot distance tables.

Every distinct fingerprint gets a table of Hamming distances to reference fingerprints, taken
separately over four 16-bit groups. Two fingerprints that differ in at most two bits agree on at
least two groups, hence in all distances of those groups: an equi-join on the distances of each of
the six pairs of groups brings every such pair together. Pairs are then discarded if any distance
differs by more than the allowed bits (triangle inequality), and survivors verified bit by bit.

Buckets with more than ``PAIR_BUCKET`` members form no pairs. Their members are linked exactly by
another way: two fingerprints differ in at most two bits if and only if both lie within one bit of
a common value, so each member is sent to the 65 values around it and all members that meet at a
value (65 at most) are linked to the least of them.
"""

from __future__ import annotations

import random

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from idfold.llm.common import ROW_UID, as_scan, join_split, settle, table, text_batches, with_row_uid
from idfold.llm.components import components

SHINGLE = 3
HASH_SEED = 42
MAX_BITS = 2
GROUPS = 4
PAIR_BUCKET = 32
#: Shingles whose bits are counted at once; bounds the memory that a very long text takes.
BLOCK = 1 << 16


def references(n: int = 8, seed: int = 20) -> list[int]:
    """Reference fingerprints: seeded random 64-bit values."""
    draw = random.Random(seed)
    return [draw.getrandbits(64) for _ in range(n)]


def fingerprint(text: str | None, *, shingle: int = SHINGLE, seed: int = HASH_SEED) -> int:
    """Majority bits of the XXH64 of a text's word shingles; 0 without words."""
    import xxhash

    words = (text or "").encode("utf-8", "surrogatepass").lower().split()  # bytes: A-Z and ASCII white space only
    if not words:
        return 0
    if len(words) < shingle:
        return xxhash.xxh64_intdigest(b" ".join(words), seed)
    digest = xxhash.xxh64_intdigest
    total, n = np.zeros(64, dtype=np.int64), len(words) - shingle + 1
    for start in range(0, n, BLOCK):
        part = words[start : start + BLOCK + shingle - 1]
        grams = map(b" ".join, zip(*[part[k : len(part) - shingle + 1 + k] for k in range(shingle)], strict=True))
        hashes = np.array([digest(g, seed) for g in grams], dtype="<u8")
        total += np.unpackbits(hashes.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(2 * total > n, bitorder="little").view("<u8")[0])


def fingerprints(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(row uid, doc_id, fp): one row per row of ``docs``; the fingerprint as a signed long."""
    chosen = with_row_uid(docs).select(ROW_UID, F.col(id_col).alias("doc_id"), F.col(text_col).alias("text"))
    kind = chosen.schema["doc_id"].dataType.simpleString()
    text_batches(docs.sparkSession)

    def run(batches):
        for batch in batches:
            fps = np.array([fingerprint(t.as_py()) for t in batch.column(2)], dtype=np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(fps, pa.int64())], names=[ROW_UID, "doc_id", "fp"])

    return chosen.mapInArrow(run, f"{ROW_UID} long, doc_id {kind}, fp long")


def _signed(x: int) -> int:
    return x - (1 << 64) if x >= 1 << 63 else x


def distance_tables(fp: Column) -> list[Column]:
    """Per group one long that packs the distances to all references, five bits each."""
    width = 64 // GROUPS
    tables = []
    for g in range(GROUPS):
        mask = F.lit(_signed(((1 << width) - 1) << (g * width)))
        packed = F.lit(0).cast("long")
        for k, ref in enumerate(references()):
            packed = packed.bitwiseOR(F.shiftleft(F.bit_count(fp.bitwiseXOR(F.lit(_signed(ref))).bitwiseAND(mask)).cast("long"), 5 * k))
        tables.append(packed)
    return tables


def _within(x: Column, y: Column) -> Column:
    """No distance of two packed tables differs by more than MAX_BITS."""
    ok = F.lit(True)
    for k in range(len(references())):
        at = lambda t, k=k: F.shiftright(t, 5 * k).bitwiseAND(F.lit(31))
        ok = ok & (F.abs(at(x) - at(y)) <= MAX_BITS)
    return ok


def near_links(distinct_fps: DataFrame) -> DataFrame:
    """(a, b) with a < b: links whose closure holds exactly the pairs within MAX_BITS bits."""
    tabled = distinct_fps.select("fp", F.array(*distance_tables(F.col("fp"))).alias("t"))
    pairs = [(i, j) for i in range(GROUPS) for j in range(i + 1, GROUPS)]
    keyed = tabled.select(
        "fp", "t", F.explode(F.array(*[F.xxhash64(F.lit(n), F.col("t")[i], F.col("t")[j]) for n, (i, j) in enumerate(pairs)])).alias("key")
    )
    sizes = settle(keyed.groupBy("key").agg(F.count("*").alias("n")).where("n > 1"))

    met = (
        keyed.join(sizes.where(F.col("n") <= PAIR_BUCKET), "key")
        .groupBy("key")
        .agg(F.sort_array(F.collect_list(F.struct("fp", "t"))).alias("m"))
    )
    # Each member with those after it: at most PAIR_BUCKET in a bucket.
    couples = met.select("m", F.posexplode("m").alias("at", "x")).select(
        "x", F.explode(F.filter(F.slice(F.col("m"), F.col("at") + 2, F.lit(PAIR_BUCKET)), lambda y: _distance_ok(F.col("x"), y))).alias("y")
    )
    few = couples.where(F.bit_count(F.col("x.fp").bitwiseXOR(F.col("y.fp"))) <= MAX_BITS).select(F.col("x.fp").alias("a"), F.col("y.fp").alias("b"))

    crowded = keyed.join(sizes.where(F.col("n") > PAIR_BUCKET).select("key"), "key", "left_semi").select("fp").distinct()
    around = F.array(F.col("fp"), *[F.col("fp").bitwiseXOR(F.lit(_signed(1 << k))) for k in range(64)])
    meeting = crowded.select("fp", F.explode(around).alias("z")).groupBy("z").agg(F.sort_array(F.collect_list("fp")).alias("m")).where("size(m) > 1")
    many = meeting.select(F.col("m")[0].alias("a"), F.explode(F.expr("slice(m, 2, size(m) - 1)")).alias("b"))
    return few.unionByName(many).distinct()


def _distance_ok(x: Column, y: Column) -> Column:
    ok = F.lit(True)
    for g in range(GROUPS):
        ok = ok & _within(x["t"][g], y["t"][g])
    return ok


def near_dedup(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per row of ``docs``: doc_id, fingerprint, component_id, root and the row's uid.

    component_id is the least doc_id among the texts reachable over links of at most two bits, the
    row itself included (null only if all of them are null). Texts without words, null ones too,
    share the fingerprint zero and link like any other. root is the component's least fingerprint (a
    signed long). Repeated rows and repeated doc_ids are kept;
    an empty table gives an empty result; other columns are ignored.
    """
    keyed = settle(fingerprints(as_scan(docs), id_col=id_col, text_col=text_col))
    firsts = settle(keyed.groupBy("fp").agg(F.min("doc_id").alias("least"), F.count("*").alias("n")))
    labels = components(near_links(firsts))
    rooted = firsts.join(labels.withColumnRenamed("node", "fp"), "fp", "left").select("fp", "least", "n", F.coalesce("label", "fp").alias("root"))
    heads = rooted.groupBy("root").agg(F.min("least").alias("component_id"))
    ids = settle(rooted.join(heads, "root").select("fp", "root", "component_id", "n"))
    # A fingerprint that very many rows share (of no words, or of a mass copy) meets in no task.
    return join_split(keyed, ids, "fp", count="n").select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id", "root", ROW_UID)


def keep_first(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of ``docs`` that stay, one of each component, with all their columns.

    The row of the least doc_id stays, of several such rows the first in scan order; components
    whose doc_ids are all null keep their first row.
    """
    docs = as_scan(docs)
    best = F.struct(F.col("doc_id").isNull().alias("a"), F.col("doc_id").alias("b"), F.col(ROW_UID).alias("c"))
    found = near_dedup(docs, id_col=id_col, text_col=text_col)
    kept = found.groupBy("root").agg(F.min(best).alias("best")).select(F.col("best.c").alias(ROW_UID))
    return with_row_uid(docs).join(kept, ROW_UID, "left_semi").drop(ROW_UID)


def op1_simhash_pivots(spark, sf_dir: str) -> DataFrame:
    return near_dedup(table(spark, sf_dir, "documents")).select("doc_id", "fingerprint", "component_id")
