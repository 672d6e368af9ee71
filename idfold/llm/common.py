"""Helpers that the operators of this subpackage share."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: The white space that separates words, as a Java pattern and as plain characters.
SPACE_PATTERN = r"[\x20\x09-\x0D]+"
SPACE_CHARS = " \t\n\x0b\x0c\r"

#: Name of the row number that ``with_row_uid`` adds; unlikely to clash with a caller's column.
ROW_UID = "__row_uid"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir, which must be set."""
    context = spark.sparkContext
    current = context._jsc.sc().getCheckpointDir()
    if current.isDefined():
        return current.get()
    configured = spark.conf.get("spark.checkpoint.dir", None)
    if not configured:
        if context.master != "local" and not context.master.startswith("local["):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        configured = tempfile.mkdtemp(prefix="idfold-checkpoints-")  # one process is driver and executor
    context.setCheckpointDir(configured)
    return context._jsc.sc().getCheckpointDir().get()


def settle(df: DataFrame) -> DataFrame:
    """Write ``df`` once as Parquet in the shared folder and return a scan of it.

    Cuts the lineage so that a lost executor does not cause upstream work to be redone, and gives
    the planner true sizes for its choice of joins.
    """
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/idfold-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


#: Rows of an Arrow batch where rows hold whole texts: bounds the buffers on both sides.
TEXT_BATCH_ROWS = 1024


def text_batches(spark: SparkSession) -> None:
    """Lower the rows per Arrow batch of the session for stages that hand whole texts to workers.

    The setting is read when a query runs, not when it is built, so it stays lowered; callers that
    want another value set it again.
    """
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if not 0 < int(spark.conf.get(key, "10000")) <= TEXT_BATCH_ROWS:
        spark.conf.set(key, str(TEXT_BATCH_ROWS))


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """Evaluate ``value`` once per row and hand it to ``body`` (a lambda variable, never inlined)."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


def words_of(text: Column) -> Column:
    """Words of a text: maximal runs outside SPACE_PATTERN; null or blank text gives an empty array."""
    trimmed = F.btrim(F.coalesce(text, F.lit("")), F.lit(SPACE_CHARS))
    return F.when(trimmed == "", F.array().cast("array<string>")).otherwise(F.split(trimmed, SPACE_PATTERN))


#: Bits of a row number that hold the row's place in its file; the others number the files.
ROW_BITS = 40
_NARROW = ("Project", "Filter", "SubqueryAlias")


def as_scan(df: DataFrame) -> DataFrame:
    """``df`` if its rows are rows of one file scan, at most narrowed; otherwise a scan of it, written out."""
    node = df._jdf.queryExecution().analyzed()
    while node.nodeName() in _NARROW:
        node = node.children().head()
    return df if node.nodeName() == "LogicalRelation" and df.inputFiles() else settle(df)


def with_row_uid(df: DataFrame) -> DataFrame:
    """A file scan with a row number that follows from the row's file and its place in that file.

    Any later evaluation gives a row the same number, however files are split among tasks and
    whatever executors there are then. Files are numbered in order of path; the table of their
    numbers (16 bytes a file, of the list that the driver holds for any scan) is broadcast. Callers
    take ``as_scan`` of their input once and number only that. Raises for other inputs, and where
    the caller has a column of the name ROW_UID.
    """
    if ROW_UID in df.columns:
        raise ValueError(f"{ROW_UID} is the name of the row number")
    path, place = F.col("_metadata.file_path"), F.col("_metadata.row_index")
    paths = sorted(r[0] for r in df.select(path.alias("path")).distinct().collect())
    if len(paths) <= 1:
        return df.withColumn(ROW_UID, place)
    files = df.sparkSession.createDataFrame(list(enumerate(paths)), "__file long, __path string")
    hashed = lambda seed: files.select(F.xxhash64("__path", F.lit(seed)).alias("__key"), "__file")
    seed = next(k for k in range(64) if hashed(k).select("__key").distinct().count() == len(paths))
    joined = df.select("*", F.xxhash64(path, F.lit(seed)).alias("__key"), place.alias("__place")).join(F.broadcast(hashed(seed)), "__key")
    return joined.select(*[F.col(f"`{c}`") for c in df.columns], (F.col("__file") * F.lit(1 << ROW_BITS) + F.col("__place")).alias(ROW_UID))


#: Keys that hold a larger share of all rows than this are joined by broadcast (as many at most, inverted).
HOT_SHARE = 1 / 1024


def join_split(rows: DataFrame, heads: DataFrame, key: str, *, count: str, hot_share: float = HOT_SHARE) -> DataFrame:
    """Inner join of ``rows`` with ``heads``, one row per key with the number of its rows in ``count``.

    The heads of hot keys (at most 1 / ``hot_share`` of them, whatever the size) are broadcast, so no
    hot key meets in one task; the others join by an ordinary shuffle. Both tables should be scans.
    """
    total = heads.agg(F.sum(count)).first()[0] or 0
    least = max(2, int(total * hot_share) + 1)
    hot = F.broadcast(heads.where(F.col(count) >= least))
    rest = rows.join(F.broadcast(heads.where(F.col(count) >= least).select(key)), key, "left_anti").join(heads.where(F.col(count) < least), key)
    return rows.join(hot, key).unionByName(rest)


def unit_draw(*parts: Column) -> Column:
    """Uniform number in (0, 1) from the MD5 of the parts; the same in any engine that has MD5."""
    digest = F.md5(F.concat_ws(":", *[p.cast("string") for p in parts]).cast("binary"))
    high = F.conv(F.substring(digest, 1, 12), 16, 10).cast("bigint")
    return (high + F.lit(0.5)) / F.lit(float(1 << 48))
