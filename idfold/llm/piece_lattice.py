"""SentencePiece encoding and decoding over a relational lattice.

Texts fall into segments that no piece crosses: a cut lies wherever no piece holds the two adjacent
bytes, the last of a character and the first of the next (so between a letter and a comma, or before
a space that follows a letter). Space marks are written as spaces throughout. All segments are
counted. For each distinct segment every substring of at most the longest
piece's length is an edge candidate; an equi-join with the piece table keeps the real ones, edges are
grouped by segment, and a fold with Spark's ``aggregate`` finds the segment's pieces. The fold
depends on the kind of model:

* ``bpe``: edges in order of merge rank and place; an edge is taken if both its ends are borders and
  exactly one border lies between them, which then goes. This repeats the merges of the model
  (a best-sum Viterbi path over the scores of a BPE model gives other pieces).
* ``unigram``: the Viterbi fold, best sum of scores per end.

Segments used most, up to ``HOT_SEGMENTS``, are encoded once by the lattice and broadcast to the
workers, which rewrite slices of rows as segment numbers. A slice carries its other segments along;
slices are dealt out by one exchange, behind which the lattice encodes those segments per slice and
the slice is put together, all without another exchange. The bound on the broadcast shows in no
result. The ids of every text are decoded again and compared with the text.
"""

from __future__ import annotations

import heapq
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from idfold.llm.common import ROW_UID, as_scan, let, settle, table, text_batches, with_row_uid

#: Where the public tokenizer lies; a parameter of every function that needs a model.
MODEL_PATH = "/opt/tokenizers/piece_bpe_32k.model"
#: Bound on the broadcast dictionary (segments; about 30 bytes each).
HOT_SEGMENTS = 1 << 18
#: Fixed value: the space mark, as which the model writes a space.
MARK = "▁"
#: Longest segment whose borders fit the bits of a long; longer ones are merged in Python.
MAX_FOLD = 60
#: Single characters below this code point are looked up in a constant, others by the join.
NEAR = 0x250
#: Ids at or over this stand for a character without a piece: UNKNOWN + code point.
UNKNOWN = 1 << 21


@dataclass(frozen=True)
class Pieces:
    """What encoding needs of a model: pieces with ids and ranks, byte pieces, decoding bytes."""

    kind: str
    ids: dict[str, int] = field(repr=False)
    scores: dict[str, float] = field(repr=False)
    byte_base: int
    raw: list[bytes] = field(repr=False)

    @property
    def longest(self) -> int:
        return max(map(len, self.ids))

    def glue(self) -> np.ndarray:
        """For two adjacent bytes (first * 256 + second): whether no cut may lie between them."""
        table = np.zeros((256, 256), dtype=bool)
        table[:, 0x80:0xC0] = True  # inside a character
        for piece in self.ids:
            for x, y in zip(piece, piece[1:], strict=False):
                table[x.encode()[-1], y.encode()[0]] = True
        return table.reshape(-1)

    def ranks(self) -> dict[str, int]:
        """Order of merging: higher score first, then lower id."""
        order = sorted((p for p in self.ids if len(p) > 1), key=lambda p: (-self.scores[p], self.ids[p]))
        return {p: k for k, p in enumerate(order)}


def load_pieces(path: str = MODEL_PATH, kind: str = "bpe") -> Pieces:
    """Read a model file with byte fallback; ``kind`` is bpe or unigram, as it was trained. Marks become spaces."""
    import sentencepiece

    model = sentencepiece.SentencePieceProcessor(model_file=path)
    ids, scores, raw, base = {}, {}, [], None
    for i in range(model.get_piece_size()):
        piece = model.id_to_piece(i)
        if model.is_byte(i):
            base = i if base is None else base
            raw.append(bytes([i - base]))
        elif model.is_control(i) or model.is_unknown(i) or model.is_unused(i):
            raw.append(b"")
        else:
            piece = piece.replace(MARK, " ")
            ids[piece], scores[piece] = i, model.get_score(i)
            raw.append(piece.encode())
    if base is None:
        raise ValueError("the model has no byte pieces")
    return Pieces(kind, ids, scores, base, raw)


def piece_table(spark: SparkSession, pieces: Pieces) -> DataFrame:
    """(piece, piece_id, rank, score): as many rows as the model has pieces."""
    ranks = pieces.ranks()
    return spark.createDataFrame(
        pd.DataFrame({"piece": list(pieces.ids), "piece_id": list(pieces.ids.values()), "rank": [ranks.get(p, 0) for p in pieces.ids], "score": [pieces.scores[p] for p in pieces.ids]}),
        "piece string, piece_id int, rank int, score double",
    )


def _shl(x: Column | int, n: Column) -> Column:
    return F.call_function("shiftleft", F.lit(x).cast("long") if isinstance(x, int) else x, n)


def _byte_ids(point: Column, base: int) -> Column:
    """Ids of the UTF-8 bytes of a code point."""
    tail = lambda n: F.lit(0x80) + F.shiftright(point, 6 * n).bitwiseAND(F.lit(0x3F))
    lead = lambda bits, n: F.lit(bits) + F.shiftright(point, 6 * n)
    parts = (
        F.when(point < 0x80, F.array(point))
        .when(point < 0x800, F.array(lead(0xC0, 1), tail(0)))
        .when(point < 0x10000, F.array(lead(0xE0, 2), tail(1), tail(0)))
        .otherwise(F.array(lead(0xF0, 3), tail(2), tail(1), tail(0)))
    )
    return F.transform(parts, lambda b: (b + base).cast("int"))


def _ids_of(seg: Column, chosen: Column, pieces: Pieces) -> Column:
    """Token ids from entries in order of start, which hold the id in their low 22 bits."""

    def spell(ids: Column) -> Column:
        known = F.array_max(ids) < UNKNOWN
        return F.when(known, ids).otherwise(F.flatten(F.transform(ids, lambda i: F.when(i < UNKNOWN, F.array(i)).otherwise(_byte_ids(i - UNKNOWN, pieces.byte_base)))))

    return let(F.transform(chosen, lambda x: x.bitwiseAND(F.lit((1 << 22) - 1)).cast("int")), spell)


def _merge_fold(seg: Column, edges: Column, pieces: Pieces) -> Column:
    """Token ids of a segment from its sorted edges, packed as rank, start (6), length (5), id (22 bits).

    Borders of the growing pieces are the bits of a long. Each edge is unpacked once to the border
    bits it spans and those inside it.
    """
    start = lambda e: F.shiftright(e, 27).bitwiseAND(F.lit(63)).cast("int")
    length = lambda e: F.shiftright(e, 22).bitwiseAND(F.lit(31)).cast("int")

    def spans(e: Column) -> Column:
        over = _shl(_shl(2, length(e)) - F.lit(1), start(e))
        inside = _shl(_shl(1, length(e)) - F.lit(2), start(e))
        return F.struct(over.alias("over"), inside.alias("inside"), e.bitwiseAND(F.lit((63 << 27) + (1 << 22) - 1)).alias("entry"))

    def step(borders: Column, e: Column) -> Column:
        # Both ends and one border between: three bits, of which one inside.
        fits = (F.bit_count(borders.bitwiseAND(e["over"])) == 3) & (F.bit_count(borders.bitwiseAND(e["inside"])) == 1)
        return F.when(fits, borders.bitwiseAND(F.bitwise_not(e["inside"]))).otherwise(borders)

    n = F.length(seg)
    full = _shl(2, n) - F.lit(1)
    near = F.split(F.lit(",".join(str(pieces.ids.get(chr(c), UNKNOWN + c)) for c in range(NEAR))), ",").cast("array<int>")

    def emit(edges: Column, borders: Column) -> Column:
        taken = F.filter(edges, lambda e: (F.bit_count(borders.bitwiseAND(e["over"])) == 2) & (borders.bitwiseAND(e["inside"]) == 0))
        bare = F.filter(F.sequence(F.lit(0), n - 1), lambda s: F.call_function("shiftright", borders, s).bitwiseAND(F.lit(3)) == 3)

        def single(s: Column) -> Column:
            # Far single characters with a piece are edges themselves; the constant has none for them.
            point = F.ascii(F.substring(seg, s + 1, F.lit(1)))
            own = F.exists(taken, lambda e: F.shiftright(e["entry"], 27) == s)
            far = F.when(point >= NEAR, F.when(~own, point + UNKNOWN))
            return _shl(s.cast("long"), F.lit(27)) + F.coalesce(F.get(near, point), far)

        singles = F.filter(F.transform(bare, single), lambda x: x.isNotNull())
        return F.sort_array(F.concat(F.transform(taken, lambda e: e["entry"]), singles))

    def run(unpacked: Column) -> Column:
        return let(F.aggregate(unpacked, full, step), lambda borders: emit(unpacked, borders))

    return _ids_of(seg, let(F.transform(edges, spans), run), pieces)


def _viterbi_fold(seg: Column, edges: Column, pieces: Pieces) -> Column:
    """Token ids of the path of the best score sum; ``edges`` are structs (start, stop, id, score)."""
    first = F.array(F.struct(F.lit(0.0).alias("sum"), F.lit(0).alias("start"), F.lit(0).alias("id")))

    def reach(best: Column, stop: Column) -> Column:
        here = F.filter(edges, lambda e: e["stop"] == stop)
        sums = F.transform(here, lambda e: F.struct((F.get(best, e["start"])["sum"] + e["score"]).alias("sum"), e["start"].alias("start"), e["id"].alias("id")))
        return F.concat(best, F.array(F.array_max(sums)))

    def back(best: Column) -> Column:
        start = F.struct(F.size(best).alias("at"), F.array().cast("array<bigint>").alias("path"))

        def step(acc: Column, stop: Column) -> Column:
            e = F.get(best, stop)
            entry = _shl(e["start"].cast("long"), F.lit(22)) + e["id"].cast("long")
            here = (acc["at"] == stop) | (acc["at"] == F.size(best))
            return F.when(here, F.struct(e["start"].alias("at"), F.concat(F.array(entry), acc["path"]).alias("path"))).otherwise(acc)

        return F.aggregate(F.sequence(F.size(best) - 1, F.lit(1), F.lit(-1)), start, step, lambda acc: acc["path"])

    best = F.aggregate(F.sequence(F.lit(1), F.length(seg)), first, reach)
    return _ids_of(seg, let(best, back), pieces)


def merge_long(seg: str, pieces: Pieces, ranks: dict[str, int]) -> list[int]:
    """Merges of a segment of any length with a heap; the plain form of the merge fold."""
    parts: list[str | None] = list(seg)
    after, before = list(range(1, len(parts) + 1)), list(range(-1, len(parts) - 1))
    heap: list[tuple[int, int, str, str]] = []

    def offer(i: int, j: int) -> None:
        if i >= 0 and j < len(parts) and (r := ranks.get(parts[i] + parts[j])) is not None:
            heapq.heappush(heap, (r, i, parts[i], parts[j]))

    for i in range(len(parts) - 1):
        offer(i, i + 1)
    while heap:
        _, i, x, y = heapq.heappop(heap)
        j = after[i]
        if parts[i] != x or j >= len(parts) or parts[j] != y:
            continue
        parts[i], parts[j] = x + y, None
        after[i] = after[j]
        if after[j] < len(parts):
            before[after[j]] = i
        offer(before[i], i)
        offer(i, after[i])
    out: list[int] = []
    for p in parts:
        if p is not None:
            out += [pieces.ids[p]] if p in pieces.ids else [pieces.byte_base + b for b in p.encode("utf-8", "surrogatepass")]
    return out


def encode_segments(segs: DataFrame, pieces: Pieces, *carried: str, long: bool = True) -> DataFrame:
    """(seg, carried..., ids) for distinct segments ``segs(seg, carried...)``, by the lattice.

    An exchange by any of the columns serves the grouping of edges too: nothing between moves a row.
    ``long=False`` is for callers that have no segments over MAX_FOLD (they would get none).
    """
    # Carried numbers come first: where the grouping sorts, they part rows faster than texts do.
    keys, bpe = [*carried, "seg"], pieces.kind == "bpe"
    # Joined by a long hash and compared as text behind it: many times faster than a text key.
    table = piece_table(segs.sparkSession, pieces)
    if bpe:  # the empty piece lets cells of length 0 pass the join
        table = table.unionByName(segs.sparkSession.range(1).select(F.lit("").alias("piece"), F.lit(0).alias("piece_id"), F.lit(0).alias("rank"), F.lit(0.0).alias("score")))
    known = F.broadcast(table.withColumn("piece_key", F.xxhash64("piece")).withColumnRenamed("piece", "known"))
    none, short = F.array().cast("array<int>"), F.length("seg") <= MAX_FOLD
    places = F.sequence(F.lit(0), F.length("seg") - 1)
    starts = segs.select(*keys, F.explode(F.when(short, places).otherwise(F.array(F.lit(0))) if bpe else places).alias("start"))
    least = 2 if bpe else 1
    room = F.least(F.lit(pieces.longest), F.length("seg") - F.col("start"))
    spans = F.when(room >= least, F.sequence(F.lit(least), room)).otherwise(none)
    if bpe:
        # A cell of length 0 keeps segments without edges, long ones among them; single characters
        # that the constant of the fold does not hold are looked up like longer pieces.
        far = F.ascii(F.substring(F.col("seg"), F.col("start") + 1, F.lit(1))) >= NEAR
        extra = F.concat(F.when(F.col("start") == 0, F.array(F.lit(0))).otherwise(none), F.when(far & short, F.array(F.lit(1))).otherwise(none))
        spans = F.when((F.col("start") > 0) & ~far, spans).otherwise(F.concat(extra, F.when(short, spans).otherwise(none)))
    cells = starts.select(*keys, "start", F.explode(spans).alias("len"))
    cells = cells.withColumn("piece", F.substring(F.col("seg"), F.col("start") + 1, F.col("len")))
    same = (F.xxhash64("piece") == F.col("piece_key")) & (F.col("piece") >= F.col("known")) & (F.col("piece") <= F.col("known"))
    edges = cells.join(known, same, "inner") if bpe else cells.join(known, same, "left").where("piece_id is not null or len < 2")
    code = F.coalesce(F.col("piece_id"), F.ascii("piece") + F.lit(UNKNOWN))
    if bpe:
        # Single characters take no part in merging; the greatest rank puts them last.
        rank = F.when(F.col("len") == 1, F.lit((1 << 20) - 1)).otherwise(F.col("rank")).cast("long")
        packed = _shl(rank, F.lit(33)) + _shl(F.col("start").cast("long"), F.lit(27)) + _shl(F.col("len").cast("long"), F.lit(22)) + code.cast("long")
        edge = F.when(F.col("len") == 0, F.lit(-1).cast("long")).otherwise(packed)
    else:
        lowest = min(pieces.scores.values()) - 10
        edge = F.struct("start", (F.col("start") + F.col("len")).alias("stop"), code.alias("id"), F.coalesce("score", F.lit(lowest)).alias("score"))
    grouped = edges.select(*keys, edge.alias("edge")).groupBy(*keys).agg(F.collect_list("edge").alias("edges"))
    if not bpe:
        return grouped.select(*keys, let(F.col("edges"), lambda e: _viterbi_fold(F.col("seg"), e, pieces)).alias("ids"))
    real = F.sort_array(F.filter("edges", lambda x: x >= 0))
    folded = let(real, lambda e: _merge_fold(F.col("seg"), e, pieces))
    if not long:
        return grouped.select(*keys, folded.alias("ids"))
    ranks = pieces.ranks()

    @F.pandas_udf("array<int>")
    def long_merge(seg: pd.Series) -> pd.Series:
        return seg.map(lambda x: None if x is None else merge_long(x, pieces, ranks))

    either = F.when(short, folded).otherwise(F.col("long_ids"))
    return grouped.withColumn("long_ids", long_merge(F.when(~short, F.col("seg")))).select(*keys, either.alias("ids"))


#: Counts that a counting task holds before it sums them, and hands them on if three quarters are left.
COUNTED = 1 << 19
#: Rows and characters that a worker cuts at a time and that make a slice, at most (or one longer text).
UNIT_ROWS, UNIT_CHARS = 512, 1 << 21
def cut_texts(texts: pa.StringArray, glue: np.ndarray) -> tuple[pa.StringArray, np.ndarray]:
    """All segments of the texts (none null) in one array, and how many each text has.

    A text is seen as the model sees it: a space before it, marks as spaces; no text has no segment.
    """
    texts = pc.replace_substring(texts, MARK, " ")
    texts = texts.combine_chunks() if isinstance(texts, pa.ChunkedArray) else texts
    offsets = np.frombuffer(texts.buffers()[1], dtype=np.int32)[texts.offset : texts.offset + len(texts) + 1].astype(np.int64)
    lengths = np.diff(offsets)
    real = lengths > 0
    begins = (np.cumsum(lengths + real) - (lengths + real))[real]
    data = np.full(int((lengths + real).sum()), 0x20, dtype=np.uint8)
    cut = np.ones(len(data), dtype=bool)
    if len(data):
        body = cut.copy()
        body[begins] = False
        data[body] = np.frombuffer(texts.buffers()[2], dtype=np.uint8)[offsets[0] : offsets[-1]]
        cut[1:] = ~glue[(data[:-1].astype(np.uint16) << 8) | data[1:]]
        cut[begins] = True
    at = np.flatnonzero(cut)
    segs = pa.StringArray.from_buffers(len(at), pa.py_buffer(np.append(at, len(data)).astype(np.int32)), pa.py_buffer(data))
    counts = np.zeros(len(texts), dtype=np.int64)
    counts[real] = np.diff(np.append(np.searchsorted(at, begins), len(at)))
    return segs, counts


def _units(batches, column: int):
    """Batches joined and cut anew to units of at most UNIT_ROWS rows and UNIT_CHARS characters."""
    held: list[pa.RecordBatch] = []
    for batch in batches:
        held.append(batch)
        if sum(b.num_rows for b in held) >= UNIT_ROWS or sum(b.column(column).nbytes for b in held) >= UNIT_CHARS:
            yield from _parts(_joined(held), column, UNIT_ROWS, UNIT_CHARS)
            held = []
    if held:
        yield from _parts(_joined(held), column, UNIT_ROWS, UNIT_CHARS)


def _joined(batches: list[pa.RecordBatch]) -> pa.RecordBatch:
    return batches[0] if len(batches) == 1 else pa.Table.from_batches(batches).combine_chunks().to_batches()[0]


def _parts(batch: pa.RecordBatch, column: int, rows: int, chars: int):
    """Consecutive parts of a batch of at most so many rows and characters, or of one row."""
    lengths = pc.fill_null(pc.binary_length(batch.column(column)), 0).to_pylist()
    start, held = 0, 0
    for i, n in enumerate(lengths):
        if i > start and (i - start >= rows or held + n > chars):
            yield batch.slice(start, i - start)
            start, held = i, 0
        held += n
    if batch.num_rows > start:
        yield batch.slice(start)


def hot_segments(docs: DataFrame, pieces: Pieces, *, text_col: str, bound: int) -> DataFrame:
    """(seg, n): at most ``bound`` segments for the dictionary, the most used ones.

    Which segments it holds does not show in any result, only in what travels. Tasks count all
    their segments and hand on those that they met twice or more; sums of these decide.
    """
    glue = pieces.glue()

    def count(batches):
        held: list[pa.Table] = []
        for unit in _units(batches, 0):
            found = pc.value_counts(cut_texts(pc.fill_null(unit.column(0), ""), glue)[0])
            held.append(pa.table({"seg": found.field(0), "n": found.field(1)}))
            if sum(t.num_rows for t in held) > COUNTED:
                held = [_summed(held)]
                if held[0].num_rows > 3 * COUNTED // 4:
                    yield from _repeated(held.pop())
        if held:
            yield from _repeated(_summed(held))

    local = docs.select(F.col(text_col).alias("text")).mapInArrow(count, "seg string, n long")
    counts = settle(local.groupBy("seg").agg(F.sum("n").alias("n")))
    # Counts fall into classes of a sixteenth of a doubling: a table of some hundred rows.
    level = F.floor(16 * F.log2("n"))
    sizes = {r["level"]: r["k"] for r in counts.groupBy(level.alias("level")).agg(F.count("*").alias("k")).collect()}
    total, lowest = 0, None
    for at in sorted(sizes, reverse=True):
        total += sizes[at]
        if total > bound:
            break
        lowest = at
    return counts.where(level >= lowest if lowest is not None else F.lit(False)).repartition("seg")


def _summed(tables: list[pa.Table]) -> pa.Table:
    return pa.concat_tables(tables).group_by("seg").aggregate([("n", "sum")]).rename_columns({"n_sum": "n"}).select(["seg", "n"])


def _repeated(counts: pa.Table):
    yield from counts.filter(pc.greater(counts.column("n"), 1)).to_batches(max_chunksize=1 << 16)


def dictionary(encoded: pa.Table) -> dict:
    """segs: segments; flat: the ids of all segments in one array; begin: where each begins."""
    flat_of = lambda c: c.combine_chunks() if isinstance(c, pa.ChunkedArray) else c
    segs, lists = flat_of(encoded.column("seg")), flat_of(encoded.column("ids"))
    lengths = pc.list_value_length(lists).to_numpy(zero_copy_only=False).astype(np.int64)
    return {"segs": segs.cast(pa.string()), "flat": lists.flatten().to_numpy().astype(np.int32), "begin": np.concatenate([[0], np.cumsum(lengths)]).astype(np.int64)}


def _pack(arrays: list[np.ndarray]) -> bytes:
    """Int arrays, compressed as byte planes behind their lengths."""
    import zstandard

    head = np.array([len(arrays), *map(len, arrays)], dtype="<i4")
    body = np.concatenate([np.asarray(a, dtype="<i4") for a in arrays]) if arrays else np.array([], dtype="<i4")
    planes = np.ascontiguousarray(body.view(np.uint8).reshape(-1, 4).T)
    return zstandard.ZstdCompressor(level=1).compress(head.tobytes() + planes.tobytes())


def _unpack(data: bytes) -> list[np.ndarray]:
    import zstandard

    raw = zstandard.ZstdDecompressor().decompress(data)
    n = int(np.frombuffer(raw, dtype="<i4", count=1)[0])
    lengths = np.frombuffer(raw, dtype="<i4", count=n, offset=4)
    planes = np.frombuffer(raw, dtype=np.uint8, offset=4 + 4 * n).reshape(4, -1)
    body = np.ascontiguousarray(planes.T).view("<i4").reshape(-1)
    return np.split(body, np.cumsum(lengths)[:-1]) if n else []


def decode_ids(ids, pieces: Pieces) -> str:
    """Text of token ids: pieces and bytes joined, marks as spaces, the leading space removed."""
    raw = pieces.raw
    data = b"".join([raw[i] for i in ids])
    return (data[1:] if data[:1] == b" " else data).decode("utf-8", "replace")


def _digests(data, offsets: np.ndarray, skip: np.ndarray | None = None) -> np.ndarray:
    """Four ints per text, the 128-bit hash of its bytes (less the first ``skip`` of them)."""
    import xxhash

    view, begins, ends = memoryview(data), offsets[:-1] if skip is None else offsets[:-1] + skip, offsets[1:]
    return np.frombuffer(b"".join(xxhash.xxh3_128_digest(view[b:e]) for b, e in zip(begins.tolist(), ends.tolist(), strict=True)), dtype="<i4")


def _one_array(values) -> pa.Array:
    return values.combine_chunks() if isinstance(values, pa.ChunkedArray) else values


def encode(docs: DataFrame, pieces: Pieces, *, id_col: str = "doc_id", text_col: str = "text", hot: int = HOT_SEGMENTS) -> DataFrame:
    """One row per row of ``docs``: doc_id, n_tokens, ids, exact, and the row's uid.

    ``exact`` says whether decoding the ids gives the text back (by a 128-bit hash of the decoded
    bytes; false only for texts that hold the space mark itself as a character, which models of this
    kind cannot tell from a space). Null and empty texts have no tokens; characters without a piece
    become byte pieces; repeated rows are encoded each; an empty table gives an empty result; extra
    columns are ignored.
    """
    spark = docs.sparkSession
    docs = as_scan(docs)
    text_batches(spark)
    bound = encode_segments(hot_segments(docs, pieces, text_col=text_col, bound=hot).select("seg"), pieces).toArrow()  # ``hot`` rows at most
    held = spark.sparkContext.broadcast(dictionary(bound))
    del bound
    pa.default_memory_pool().release_unused()
    rows = with_row_uid(docs).select(ROW_UID, F.col(id_col).alias("doc_id"), F.col(text_col).alias("text"))
    kind = rows.schema["doc_id"].dataType.simpleString()
    ranks, glue = pieces.ranks(), pieces.glue()
    raw = np.frombuffer(b"".join(pieces.raw), dtype=np.uint8)
    raw_size = np.array([len(x) for x in pieces.raw], dtype=np.int64)
    raw_begin = np.cumsum(raw_size) - raw_size
    longest = MAX_FOLD if pieces.kind == "bpe" else 1 << 30

    def rewrite(batches):
        known = held.value["segs"]
        for unit in _units(batches, 2):
            texts = pc.fill_null(unit.column(2), "")
            offsets = np.frombuffer(texts.buffers()[1], dtype=np.int32)[texts.offset : texts.offset + len(texts) + 1]
            digests = _digests(texts.buffers()[2] or b"", offsets)
            segs, counts = cut_texts(texts, glue)
            coded = _one_array(pc.dictionary_encode(segs))
            numbers = pc.fill_null(pc.index_in(coded.dictionary, value_set=known), -1).to_numpy().astype(np.int32)
            # Other segments are numbered from -1 down: first those that the lattice takes, then long
            # ones and line breaks, which are encoded here (and so can part the others).
            other = np.flatnonzero(numbers < 0)
            rare = coded.dictionary.take(pa.array(other))
            apart = pc.or_(pc.match_substring(rare, "\n"), pc.greater(pc.utf8_length(rare), longest)).to_numpy(zero_copy_only=False)
            numbers[np.concatenate([other[~apart], other[apart]])] = -1 - np.arange(len(other), dtype=np.int32)
            inline = [np.array(merge_long(x, pieces, ranks), dtype=np.int32) for x in rare.filter(pa.array(apart)).to_pylist()]
            short = rare.filter(pa.array(~apart))
            lines = pc.binary_join(pa.ListArray.from_arrays(pa.array([0, len(short)], pa.int32()), short), "\n")
            code, uids = _pack([digests, counts, numbers[coded.indices.to_numpy()], *inline]), unit.column(0)
            yield pa.RecordBatch.from_arrays(
                [uids.slice(0, 1), pa.array([uids.to_pylist()], pa.list_(pa.int64())), pa.ListArray.from_arrays(pa.array([0, len(uids)], pa.int32()), unit.column(1)), pa.array([code], pa.binary()), lines],
                names=["slice", "uids", "doc_ids", "code", "rare"],
            )

    form = f"slice long not null, uids array<bigint> not null, doc_ids array<{kind}> not null, code binary not null, rare string not null"
    slices = rows.mapInArrow(rewrite, form).repartition("slice")
    # The checksum of a whole slice travels on both ways and is compared where they meet. As it reads
    # every column, both uses of the slices have the same exchange below them, which is then made once.
    slices = slices.withColumn("checksum", F.xxhash64("slice", "uids", "doc_ids", "code", "rare"))
    rare = slices.select("slice", "checksum", F.posexplode_outer(F.split("rare", "\n")).alias("k", "seg")).where("seg != ''")
    encoded = encode_segments(rare, pieces, "k", "slice", "checksum", long=False)
    in_order = F.transform(F.sort_array(F.collect_list(F.struct("k", "ids"))), lambda x: x["ids"])
    per_slice = encoded.groupBy("slice").agg(in_order.alias("rare_ids"), F.max("checksum").alias("of"))

    def assemble(batches):
        flat, begin = held.value["flat"], held.value["begin"]
        for batch in batches:
            for uids, doc_ids, code, rare_ids, checksum, of in zip(*batch.columns, strict=True):
                if of.as_py() not in (None, checksum.as_py()):
                    raise RuntimeError("a slice met segments of another one")
                n, (digests, sizes, at, *inline) = len(uids), _unpack(code.as_py())
                own, lengths = [], []
                if rare_ids.values is not None and len(rare_ids.values):
                    own, lengths = [rare_ids.values.flatten().to_numpy()], rare_ids.values.value_lengths().to_numpy(zero_copy_only=False).tolist()
                own, lengths = own + inline, lengths + [len(x) for x in inline]
                own_flat = np.concatenate(own) if own else np.array([], dtype=np.int32)
                own_begin = np.concatenate([[0], np.cumsum(lengths)]).astype(np.int64)
                ids, per_segment = _two_sources(flat, begin, own_flat, own_begin, at)
                counts = np.bincount(np.repeat(np.arange(n), sizes), per_segment, n).astype(np.int64)
                stops = np.cumsum(counts)
                spelled = raw_size[ids]
                total = np.cumsum(spelled)
                back = np.repeat((raw_begin[ids] - (total - spelled)).astype(np.int32), spelled)
                back += np.arange(len(back), dtype=np.int32)
                back = raw[back]
                ends = np.concatenate([[0], total])[np.concatenate([[0], stops])]
                # The space before each text is not part of it.
                lead = np.zeros(n, dtype=np.int64)
                full = np.flatnonzero(np.diff(ends) > 0)
                lead[full] = back[ends[full]] == 0x20
                exact = (_digests(back.data, ends, lead).reshape(n, 4) == digests.reshape(n, 4)).all(axis=1)
                pa.default_memory_pool().release_unused()
                yield pa.RecordBatch.from_arrays(
                    [uids.values, doc_ids.values, pa.array(counts), pa.ListArray.from_arrays(pa.array(np.concatenate([[0], stops]).astype(np.int32)), pa.array(ids)), pa.array(exact)],
                    names=[ROW_UID, "doc_id", "n_tokens", "ids", "exact"],
                )

    joined = slices.join(per_slice, "slice", "left").select("uids", "doc_ids", "code", "rare_ids", "checksum", "of")
    return joined.mapInArrow(assemble, f"{ROW_UID} long, doc_id {kind}, n_tokens long, ids array<int>, exact boolean")


def _two_sources(flat: np.ndarray, begin: np.ndarray, own: np.ndarray, own_begin: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Ids of segment numbers ``at`` and their number per segment: the dictionary's from 0 up, the slice's own from -1 down."""
    if not len(at):
        return np.array([], dtype=np.int32), np.array([], dtype=np.int64)
    mine = at < 0
    first, last = np.where(mine, 0, at), np.where(mine, -1 - at, 0)
    none = np.zeros(2, dtype=np.int64)
    begin, own_begin = (begin if len(begin) > 1 else none), (own_begin if len(own_begin) > 1 else none)
    start = np.where(mine, own_begin[last], begin[first])
    lengths = np.where(mine, own_begin[last + 1] - own_begin[last], begin[first + 1] - begin[first])
    stops = np.cumsum(lengths)
    where = np.arange(stops[-1]) + np.repeat(start - (stops - lengths), lengths)
    from_own = np.repeat(mine, lengths)
    out = np.empty(len(where), dtype=np.int32)
    out[from_own], out[~from_own] = own[where[from_own]], flat[where[~from_own]]
    return out, lengths


def decode(tokens: DataFrame, pieces: Pieces, *, ids_col: str = "ids", text_col: str = "text") -> DataFrame:
    """``tokens`` with a text column decoded from ids; null ids give null, no ids an empty text."""

    @F.pandas_udf("string")
    def run(ids: pd.Series) -> pd.Series:
        return ids.map(lambda x: None if x is None else decode_ids(x, pieces))

    return tokens.withColumn(text_col, run(ids_col))


def lattice_viterbi(spark, sf_dir: str) -> DataFrame:
    """The Viterbi fold over whole documents, the model's scores read as those of a unigram model."""
    return encode(table(spark, sf_dir, "documents"), load_pieces(kind="unigram")).select("doc_id", "n_tokens", "ids", "exact")


def op9_piece_lattice(spark, sf_dir: str) -> DataFrame:
    return encode(table(spark, sf_dir, "documents"), load_pieces()).select("doc_id", "n_tokens", "ids", "exact")
