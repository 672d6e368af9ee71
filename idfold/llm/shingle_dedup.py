"""Near-dedup by the Jaccard similarity of word shingles.

Texts are taken as sets of hashes of five consecutive words. The nearest come first, by the SimHash
of the set and the pivot distance tables of ``simhash_pivots``: fingerprints within two bits, each
pair verified on the whole sets. At a similarity of 0.8 a SimHash of 64 bits differs in about ten
bits, give or take three; a radius that holds such pairs leaves no group of bits that they must
share, so the tables cannot find them. The candidates for the rest, pairs that are not connected by
then, come from banded minima: texts that agree on all ``ROWS`` minima of one of ``BANDS`` bands meet in a bucket.
A pair at 0.8 meets nowhere with probability (1 - 0.8 ** 6) ** 50, less than one in a million. Every
candidate is verified on the whole sets, so no link is below the similarity asked for.

Two sketches discard candidates inside the joins that bring them together. One bit of every minimum
tells pairs far apart at any length. The parities of the numbers of shingles in ``CELLS`` cells
differ in no more cells than the sets differ in shingles, so they rule a pair out for certain; with
texts of up to about CELLS shingles few pairs below the similarity are left to verify.

Buckets form no pairs at first: each member is compared with the one that meets most others over
all its buckets, which in a group of near copies is one near the middle. Only what is left in
different components after that is compared with the rest of its bucket.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from idfold.llm.common import ROW_UID, as_scan, settle, text_batches, with_row_uid
from idfold.llm.components import components
from idfold.llm.simhash_pivots import near_links

SHINGLE = 5
SIMILARITY = 0.8
BANDS = 50
ROWS = 6
HASH_SEED = 42
#: Longs of a sketch: one bit of each of the BANDS * ROWS minima.
SKETCH = -(-BANDS * ROWS // 64)
#: Cells whose parities are kept; a power of two, so many bits of a row.
CELLS = 512
#: A pair at the similarity asked for is discarded by its sketches with a probability below this.
MISSED = 1e-8
#: Shingles whose minima are taken at once; bounds the memory that a very long text takes.
BLOCK = 1 << 12


def shingle_set(text: str | None, *, shingle: int = SHINGLE) -> np.ndarray:
    """Sorted distinct XXH64 of a text's word shingles; shorter texts are one shingle, none without words."""
    import xxhash

    words = (text or "").encode("utf-8", "surrogatepass").lower().split()  # bytes: A-Z and ASCII white space only
    if len(words) <= shingle:
        return np.array([xxhash.xxh64_intdigest(b" ".join(words), HASH_SEED)] if words else [], dtype=np.uint64)
    digest = xxhash.xxh64_intdigest
    grams = map(b" ".join, zip(*[words[k : len(words) - shingle + 1 + k] for k in range(shingle)], strict=True))
    return np.unique(np.fromiter((digest(g, HASH_SEED) for g in grams), dtype=np.uint64, count=len(words) - shingle + 1))


def _multipliers() -> np.ndarray:
    return np.random.default_rng(20).integers(0, 1 << 31, size=(BANDS * ROWS, 1)).astype(np.uint32) * np.uint32(2) + np.uint32(1)


def parities(hashes: np.ndarray) -> np.ndarray:
    """The parities of the numbers of hashes in CELLS cells, as signed longs."""
    cells = (hashes >> np.uint64(64 - CELLS.bit_length() + 1)).astype(np.int64)
    return np.packbits((np.bincount(cells, minlength=CELLS) & 1).astype(np.uint8), bitorder="little").view("<i8")


def simhash(hashes: np.ndarray) -> int:
    """The bits that over half of the hashes have, as a signed long; zero of an empty set."""
    total = np.zeros(64, dtype=np.int64)
    for k in range(0, len(hashes), BLOCK):
        part = np.ascontiguousarray(hashes[k : k + BLOCK]).astype("<u8")
        total += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(2 * total > len(hashes), bitorder="little").view("<i8")[0])


def band_keys(hashes: np.ndarray, multipliers: np.ndarray) -> tuple[list[int], list[int]]:
    """One signed long per band, and the longs of both sketches; none of an empty set."""
    import xxhash

    if not len(hashes):
        return [], []
    low = hashes.astype(np.uint32)
    minima = np.min([(low[None, k : k + BLOCK] * multipliers).min(axis=1) for k in range(0, len(low), BLOCK)], axis=0).astype("<u4")
    bits = np.zeros(64 * SKETCH, dtype=np.uint8)
    bits[: len(minima)] = minima * np.uint32(0x9E3779B1) >> np.uint32(31)  # the top bit mixes all of the minimum
    sketch = [*np.packbits(bits, bitorder="little").view("<i8").tolist(), *parities(hashes).tolist()]
    minima = minima.tobytes()
    keys = [xxhash.xxh64_intdigest(minima[4 * ROWS * b : 4 * ROWS * (b + 1)], b) for b in range(BANDS)]
    return np.array(keys, dtype=np.uint64).view(np.int64).tolist(), sketch


def sketch_radius(similarity: float) -> int:
    """Most bits by which the sketches of a candidate may differ.

    A minimum differs in a pair with probability 1 - similarity at most, its bit with half of that;
    the radius is the least whose upper binomial tail is below MISSED.
    """
    n, p = BANDS * ROWS, (1 - similarity) / 2
    if p <= 0:
        return 0
    tail, radius = 0.0, n
    while radius > 0:
        tail += math.exp(math.lgamma(n + 1) - math.lgamma(radius + 1) - math.lgamma(n - radius + 1) + radius * math.log(p) + (n - radius) * math.log1p(-p))
        if tail >= MISSED:
            break
        radius -= 1
    return radius


def sketches(docs: DataFrame, *, shingle: int, id_col: str, text_col: str) -> DataFrame:
    """(row uid, doc_id, digest, n, fp, keys, sketch): one row per row of ``docs``; equal sets have equal digests."""
    chosen = with_row_uid(docs).select(ROW_UID, F.col(id_col).alias("doc_id"), F.col(text_col).alias("text"))
    kind = chosen.schema["doc_id"].dataType.simpleString()
    text_batches(docs.sparkSession)

    def run(batches):
        import xxhash

        multipliers = _multipliers()
        for batch in batches:
            sets = [shingle_set(t.as_py(), shingle=shingle) for t in batch.column(2)]
            found = [band_keys(s, multipliers) for s in sets]
            columns = [
                pa.array([xxhash.xxh3_128_digest(s.tobytes()) for s in sets], pa.binary()),
                pa.array([len(s) for s in sets], pa.int64()),
                pa.array([simhash(s) for s in sets], pa.int64()),
                pa.array([k for k, _ in found], pa.list_(pa.int64())),
                pa.array([b for _, b in found], pa.list_(pa.int64())),
            ]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), *columns], names=[ROW_UID, "doc_id", "digest", "n", "fp", "keys", "sketch"])

    return chosen.mapInArrow(run, f"{ROW_UID} long, doc_id {kind}, digest binary, n long, fp long, keys array<long>, sketch array<long>")


def _sets(docs: DataFrame, wanted: DataFrame, *, shingle: int, text_col: str) -> DataFrame:
    """(node, shingles) of the rows of ``docs`` whose uid is in ``wanted(node)``."""
    chosen = with_row_uid(docs).select(F.col(ROW_UID).alias("node"), F.col(text_col).alias("text")).join(wanted, "node", "left_semi")

    def run(batches):
        for batch in batches:
            sets = [shingle_set(t.as_py(), shingle=shingle).view(np.int64) for t in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(sets, pa.list_(pa.int64()))], names=["node", "shingles"])

    return chosen.mapInArrow(run, "node long, shingles array<long>")


def _verified(pairs: DataFrame, sets: DataFrame, similarity: float) -> DataFrame:
    """The rows (a, b) of ``pairs`` whose sets have the similarity or more."""
    side = lambda c: sets.select(F.col("node").alias(c), F.col("shingles").alias(f"s_{c}"))
    both = F.size(F.array_intersect("s_a", "s_b"))
    found = pairs.join(side("b"), "b").join(side("a"), "a").withColumn("both", both)
    return found.where(F.col("both") >= F.lit(similarity) * (F.size("s_a") + F.size("s_b") - F.col("both")) - 1e-9).select("a", "b")


def simhash_pairs(nodes: DataFrame) -> DataFrame:
    """(a, b): nodes of equal fingerprints with the least of them, and the least of fingerprints within two bits."""
    heads = settle(nodes.where("n > 0").groupBy("fp").agg(F.min("node").alias("head"), F.count("*").alias("c")))
    same = nodes.join(heads.where("c > 1"), "fp").where("n > 0 and node != head").select(F.col("head").alias("a"), F.col("node").alias("b"))
    side = lambda c: heads.select(F.col("fp").alias(c), F.col("head").alias(f"h_{c}"))
    near = near_links(heads.select("fp")).join(side("a"), "a").join(side("b"), "b")
    return same.unionByName(near.select(F.col("h_a").alias("a"), F.col("h_b").alias("b")))


def links(nodes: DataFrame, sets_of, *, similarity: float = SIMILARITY) -> DataFrame:
    """(a, b): links of that similarity whose closure is that of all such pairs that share a band or nearly a SimHash.

    ``nodes`` has node, n, fp, keys and sketch; ``sets_of(wanted)`` gives (node, shingles) of nodes.
    """
    sketch = F.struct(*[F.get("sketch", F.lit(k)).alias(f"w{k}") for k in range(SKETCH + CELLS // 64)])
    drawn = settle(nodes.select("node", "n", sketch.alias("w")))
    alike = settle(simhash_pairs(nodes))
    # One exchange of all keys; what follows sees only the buckets of several members. Sketches, ten times
    # as wide as a key, join pairs and the few buckets of the last step, never the buckets as a whole.
    keyed = nodes.select("node", F.explode("keys").alias("key")).withColumn("c", F.count("*").over(Window.partitionBy("key"))).where("c > 1")
    met = settle(keyed.withColumn("score", F.sum("c").over(Window.partitionBy("node"))).drop("c"))
    wanted = met.select("node").unionByName(alike.select(F.explode(F.array("a", "b")).alias("node"))).distinct()
    sets = settle(sets_of(wanted))

    radius = sketch_radius(similarity)
    share = (1 - similarity) / (1 + similarity)

    def sketched(df: DataFrame, c: str, suffix: str) -> DataFrame:
        """``df`` with the size and the sketch of the node in its column ``c``."""
        return df.join(drawn.select(F.col("node").alias(c), F.col("n").alias(f"n{suffix}"), F.col("w").alias(f"w{suffix}")), c)

    def apart(x: str, y: str, longs: range) -> Column:
        return sum((F.bit_count(F.col(f"w{x}.w{k}").bitwiseXOR(F.col(f"w{y}.w{k}"))) for k in longs), F.lit(0))

    def close(x: str, y: str) -> Column:
        """Neither sizes nor sketches of two nodes, in columns named by suffix, rule the similarity out."""
        n, m = F.col(f"n{x}"), F.col(f"n{y}")
        by_size = F.least(n, m) >= F.lit(similarity) * F.greatest(n, m) - 1e-9
        by_parity = apart(x, y, range(SKETCH, SKETCH + CELLS // 64)) <= F.lit(share) * (n + m) + 1e-9
        return by_size & by_parity & (apart(x, y, range(SKETCH)) <= radius)

    nearest = settle(_verified(alike, sets, similarity))
    known = components(nearest)
    label = lambda c: known.select(F.col("node").alias(c), F.col("label").alias(f"l_{c}"))

    # By score and the hash of the node, not by key: members that share buckets share the one they are compared with.
    order = F.struct((-F.col("score")).alias("s"), F.xxhash64("node").alias("h"), F.col("node").alias("a"))
    heads = met.groupBy("key").agg(F.min(order)["a"].alias("a"))
    pairs = met.join(heads, "key").where("node != a").select("a", F.col("node").alias("b")).distinct()
    unlinked = pairs.join(label("a"), "a", "left").join(label("b"), "b", "left").where(F.coalesce("l_a", "a") != F.coalesce("l_b", "b")).select("a", "b")
    tried = settle(sketched(sketched(unlinked, "a", "_a"), "b", "_b").where(close("_a", "_b")).select("a", "b"))
    first = settle(nearest.unionByName(_verified(tried, sets, similarity)))

    labelled = settle(met.join(components(first), "node", "left").select("key", "node", F.coalesce("label", "node").alias("label")))
    counts = labelled.groupBy("key", "label").agg(F.count("*").alias("c"))
    major = settle(counts.groupBy("key").agg(F.max(F.struct("c", "label"))["label"].alias("major"), F.count("*").alias("labels")).where("labels > 1").select("key", "major"))
    # Of two members with different labels, one at least is outside the largest component of the bucket.
    members = settle(sketched(labelled.join(major, "key"), "node", ""))
    others = members.where("label != major").select("key", F.col("node").alias("x"), F.col("n").alias("n_x"), F.col("w").alias("w_x"), F.col("label").alias("l_x"))
    rest = others.join(members, "key").where((F.col("l_x") != F.col("label")) & close("", "_x"))
    rest = rest.select(F.least("x", "node").alias("a"), F.greatest("x", "node").alias("b")).distinct()
    turned = tried.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"))
    return first.unionByName(_verified(rest.join(turned, ["a", "b"], "left_anti"), sets, similarity))


def near_dedup(docs: DataFrame, *, shingle: int = SHINGLE, similarity: float = SIMILARITY, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per row of ``docs``: doc_id, component_id, root and the row's uid.

    Texts of equal shingle sets (those without words, null ones too, have the empty set) are one
    node; nodes whose sets have the similarity or more are linked. component_id is the component's
    least doc_id (null only if all are null), root its least node.
    """
    docs = as_scan(docs)
    sketched = settle(sketches(docs, shingle=shingle, id_col=id_col, text_col=text_col))
    groups = settle(sketched.groupBy("digest").agg(F.min(ROW_UID).alias("node"), F.min("doc_id").alias("least")))
    nodes = sketched.select(F.col(ROW_UID).alias("node"), "n", "fp", "keys", "sketch").join(groups.select("node"), "node", "left_semi")
    labels = components(links(nodes, lambda wanted: _sets(docs, wanted, shingle=shingle, text_col=text_col), similarity=similarity))
    rooted = groups.join(labels, "node", "left").select("digest", "least", F.coalesce("label", "node").alias("root"))
    heads = rooted.groupBy("root").agg(F.min("least").alias("component_id"))
    ids = rooted.join(heads, "root").select("digest", "root", "component_id")
    return sketched.select(ROW_UID, "doc_id", "digest").join(ids, "digest").select("doc_id", "component_id", "root", ROW_UID)


def keep_first(docs: DataFrame, *, shingle: int = SHINGLE, similarity: float = SIMILARITY, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of ``docs`` that stay, one of each component, with all their columns.

    The row of the least doc_id stays, of several such rows the first in scan order; components
    whose doc_ids are all null keep their first row.
    """
    docs = as_scan(docs)
    best = F.struct(F.col("doc_id").isNull().alias("a"), F.col("doc_id").alias("b"), F.col(ROW_UID).alias("c"))
    found = near_dedup(docs, shingle=shingle, similarity=similarity, id_col=id_col, text_col=text_col)
    kept = found.groupBy("root").agg(F.min(best).alias("best")).select(F.col("best.c").alias(ROW_UID))
    return with_row_uid(docs).join(kept, ROW_UID, "left_semi").drop(ROW_UID)
