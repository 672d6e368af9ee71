"""Sample sets over the given tables: words, order lines, events."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from idfold.plans.ordering import with_positions

WORD_PATTERN = r"\p{L}+"
TEACHER_DAYS, STUDENT_DAY, EVAL_DAY = (1, 7), 5, 8


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def word_uses(spark: SparkSession, sf_dir: str, *, days: int = 8) -> DataFrame:
    """(doc_id, day, fr, place, word): every word use; day = doc_id mod ``days`` + 1; fr = 1 for French."""
    docs = table(spark, sf_dir, "documents")
    words = F.regexp_extract_all(F.lower("text"), F.lit(WORD_PATTERN), F.lit(0))
    return docs.select(
        "doc_id", (F.col("doc_id") % days + 1).cast("int").alias("day"), F.when(F.col("lang") == "fr", 1).otherwise(0).alias("fr"), F.posexplode(words).alias("place", "word")
    )


def word_vocabulary(uses: DataFrame) -> DataFrame:
    """(id, word, accesses, fr_uses): ids are dense ranks of the words, from 0."""
    counts = uses.groupBy("word").agg(F.count("*").alias("accesses"), F.sum("fr").alias("fr_uses"))
    return with_positions(counts, ["word"]).select((F.col("pos") - 1).alias("id"), "word", "accesses", "fr_uses")


def word_samples(spark: SparkSession, sf_dir: str, *, length: int = 1, drop: int = 100, days: int = 8) -> DataFrame:
    """(sample_id, day, label, ids): runs of ``length`` words without the ``drop`` most used of days 1-7."""
    uses = word_uses(spark, sf_dir, days=days)
    vocab = word_vocabulary(uses).select("id", "word")
    heavy = uses.where(F.col("day").between(*TEACHER_DAYS)).groupBy("word").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "word").limit(drop)
    kept = uses.join(F.broadcast(heavy.select("word")), "word", "left_anti").join(vocab, "word")
    if length == 1:
        return kept.select((F.col("doc_id") * 10_000_000 + F.col("place")).alias("sample_id"), "day", F.col("fr").alias("label"), F.array("id").alias("ids"))
    by_doc = kept.groupBy("doc_id", "day", "fr").agg(F.array_sort(F.collect_list(F.struct("place", "id"))).alias("w"))
    chunks = by_doc.select("doc_id", "day", "fr", F.explode(F.expr(f"sequence(0, size(w) div {length} - 1)")).alias("c"), "w").where(F.size("w") >= length)
    return chunks.select(
        (F.col("doc_id") * 10_000_000 + F.col("c")).alias("sample_id"), "day", F.col("fr").alias("label"),
        F.transform(F.slice("w", F.col("c") * length + 1, F.lit(length)), lambda x: x["id"]).alias("ids"),
    )


def event_samples(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(sample_id, day, ts, label, user_id, event_type, k): day 1 is Thursday 2024-01-04; label: purchase."""
    ts = F.col("ts").cast("timestamp")
    return (
        table(spark, sf_dir, "events")
        .withColumn("day", (F.datediff(F.to_date("ts"), F.lit("2024-01-04")) + 1).cast("int"))
        .where("event_type in ('view', 'click', 'purchase')")
        .select(
            F.col("event_id").alias("sample_id"), "day", ts.alias("ts"), F.when(F.col("event_type") == "purchase", 1).otherwise(0).alias("label"),
            "user_id", "event_type", F.get_json_object("props", "$.k").cast("long").alias("k"),
        )
    )


def order_samples(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(sample_id, day, label, planted, part, supplier, customer, brand, type, priority, segment, nation).

    ``label`` is the return flag (no signal); ``planted`` follows hidden integer scores of part and
    customer plus portable noise. Days are eight equal spans of the ship date.
    """
    lines, orders = table(spark, sf_dir, "lineitem"), table(spark, sf_dir, "orders")
    part, customer = table(spark, sf_dir, "part"), table(spark, sf_dir, "customer")
    sp, sc = (F.col("l_partkey") * 37) % 97 - 48, (F.col("o_custkey") * 53) % 97 - 48
    noise = (((F.col("l_orderkey") * 8 + F.col("l_linenumber")) % 2147483647 * 1103515245 + 12345) % 2147483647) % 201 - 100
    first, span = "1995-01-02", F.datediff(F.lit("2001-11-05"), F.lit("1995-01-02"))
    day = F.least(F.floor(F.datediff(F.to_date("l_shipdate"), F.lit(first)) * 8 / span) + 1, F.lit(8)).cast("int")
    return (
        lines.join(orders, lines.l_orderkey == orders.o_orderkey)
        .join(part, F.col("l_partkey") == part.p_partkey)
        .join(customer, F.col("o_custkey") == customer.c_custkey)
        .select(
            (F.col("l_orderkey") * 8 + F.col("l_linenumber")).alias("sample_id"), day.alias("day"),
            F.when(F.col("l_returnflag") == "R", 1).otherwise(0).alias("label"),
            F.when(32 * (sp + sc) + sp * sc + 32 * noise > 0, 1).otherwise(0).alias("planted"),
            F.col("l_partkey").alias("part"), F.col("l_suppkey").alias("supplier"), F.col("o_custkey").alias("customer"),
            F.col("p_brand").alias("brand"), F.col("p_type").alias("type"), F.col("o_orderpriority").alias("priority"),
            F.col("c_mktsegment").alias("segment"), F.col("c_nationkey").alias("nation"),
        )
    )


def thinned(orders: DataFrame) -> DataFrame:
    """Order samples thinned so that parts of low ``part mod 200`` dominate: a skewed access pattern."""
    u = ((F.col("sample_id") % 2147483647 * 69621 + 7) % 2147483647) % 1000
    return orders.where((1 + F.col("part") % 200) * u < 1000)


def days(samples: DataFrame, lo: int, hi: int | None = None) -> DataFrame:
    return samples.where(F.col("day").between(lo, hi or lo))


def take(samples: DataFrame, n: int, *, seed: int = 0) -> DataFrame:
    """Exactly ``n`` random samples (all, if there are fewer), the same ones on every run: those of least hash.

    Hashes are counted in ranges, each a 65,536th part; the range that holds the n-th is taken apart
    again. At last only samples of one short range are ranked, so no task ever sees n of them.
    """
    hashed = samples.withColumn("__h", F.xxhash64("sample_id", F.lit(seed)))
    low, width, left = -(1 << 63), 1 << 64, n
    for _ in range(3):
        step = width >> 16
        at = F.floor((F.col("__h").cast("decimal(20,0)") - F.lit(low).cast("decimal(20,0)")) / F.lit(step).cast("decimal(20,0)")).cast("long")
        inside = hashed if width == 1 << 64 else hashed.where(F.col("__h").between(low, low + width - 1))
        counts = {r["at"]: r["k"] for r in inside.groupBy(at.alias("at")).agg(F.count("*").alias("k")).collect()}  # 65,536 rows at most
        for slot in sorted(counts):
            if left <= counts[slot]:
                low, width = low + slot * step, step
                break
            left -= counts[slot]
        else:
            return samples
        if counts[slot] <= 10_000:
            break
    whole = hashed.where(F.col("__h") < low)
    border = hashed.where(F.col("__h").between(low, low + width - 1)).orderBy("__h", "sample_id").limit(left)
    return whole.unionByName(border).drop("__h")


def first(samples: DataFrame, n: int, *, by: str = "ts") -> DataFrame:
    """The first ``n`` samples in time."""
    return samples.orderBy(by, "sample_id").limit(n)
