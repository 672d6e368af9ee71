"""Queries around the methods: sources, filters, joins, aggregates, windows, set operations, scalars."""

from __future__ import annotations

from pyspark.sql import Window as W
from pyspark.sql import functions as F

from idfold.catalog.core import word_teacher
from idfold.catalog.registry import CHAIN_SQL, EVENTS_SQL, ORDERS_SQL, USES_SQL, VOCAB_SQL, query
from idfold.functions.hashing import prehash, universal, universal_sql
from idfold.functions.vectors import bits_needed, combine, dot, norm_count
from idfold.operators import access, baselines, mapping
from idfold.sources.samples import event_samples, order_samples, table, thinned, word_uses, word_vocabulary

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
ORDER_FEATURES = ["part", "supplier", "customer", "nation"]

# ---- sources ------------------------------------------------------------------------------------


@query("src_parquet_profile", " UNION ALL ".join(f"SELECT '{t}' AS name, (SELECT count(*) FROM {t}) AS n_rows, (SELECT count(*) FROM (DESCRIBE {t})) AS n_columns" for t in TABLES))
def src_parquet_profile(spark, sf_dir):
    out = None
    for t in TABLES:
        df = table(spark, sf_dir, t)
        one = df.agg(F.count("*").alias("n_rows")).select(F.lit(t).alias("name"), "n_rows", F.lit(len(df.columns)).cast("long").alias("n_columns"))
        out = one if out is None else out.unionByName(one)
    return out


@query("src_samples_order", f"WITH {ORDERS_SQL} SELECT * FROM samples")
def src_samples_order(spark, sf_dir):
    return order_samples(spark, sf_dir)


@query("src_samples_order_skewed", f"WITH {ORDERS_SQL} SELECT part, count(*) AS uses, sum(planted)::BIGINT AS ones FROM samples WHERE (1 + part % 200) * (((sample_id % 2147483647 * 69621 + 7) % 2147483647) % 1000) < 1000 GROUP BY part")
def src_samples_order_skewed(spark, sf_dir):
    return thinned(order_samples(spark, sf_dir)).groupBy("part").agg(F.count("*").alias("uses"), F.sum("planted").alias("ones"))


@query("src_samples_event", f"WITH {EVENTS_SQL} SELECT sample_id, day, label, user_id, event_type, k FROM ev")
def src_samples_event(spark, sf_dir):
    return event_samples(spark, sf_dir).drop("ts")


@query("src_samples_word", f"WITH {USES_SQL} SELECT day, fr AS label, count(*) AS uses, count(DISTINCT word) AS words FROM uses GROUP BY ALL")
def src_samples_word(spark, sf_dir):
    return word_uses(spark, sf_dir).groupBy("day", F.col("fr").alias("label")).agg(F.count("*").alias("uses"), F.count_distinct("word").alias("words"))


@query("src_pages_host", r"SELECT page_id, regexp_extract(url, '^[a-z]+://([^/?#]*)', 1) AS host FROM pages")
def src_pages_host(spark, sf_dir):
    return table(spark, sf_dir, "pages").select("page_id", F.regexp_extract("url", "^[a-z]+://([^/?#]*)", 1).alias("host"))


@query("src_conv_roles", "SELECT role, count(*) AS turns, count(DISTINCT conv_id) AS conversations FROM conversations GROUP BY role")
def src_conv_roles(spark, sf_dir):
    return table(spark, sf_dir, "conversations").groupBy("role").agg(F.count("*").alias("turns"), F.count_distinct("conv_id").alias("conversations"))


@query("snk_parquet_csv_json_roundtrip", "SELECT 'parquet' AS format, count(*) AS n, sum(p_partkey * 31 + p_partkey % 97)::BIGINT AS checksum FROM part UNION ALL SELECT 'csv', count(*), sum(p_partkey * 31 + p_partkey % 97)::BIGINT FROM part UNION ALL SELECT 'json', count(*), sum(p_partkey * 31 + p_partkey % 97)::BIGINT FROM part")
def snk_parquet_csv_json_roundtrip(spark, sf_dir):
    """A map written in three formats and read back with a declared schema."""
    import uuid

    from idfold.schemas import FOLD_MAP
    from idfold.storage import shared_folder

    vocab = table(spark, sf_dir, "part").select(F.lit("part").alias("feature"), F.col("p_partkey").alias("id"))
    fold_map, root, out = baselines.modulo(vocab, 97), f"{shared_folder(spark)}/idfold-sink-{uuid.uuid4().hex}", None
    for fmt in ("parquet", "csv", "json"):
        fold_map.write.format(fmt).save(f"{root}/{fmt}")
        back = spark.read.schema(FOLD_MAP).format(fmt).load(f"{root}/{fmt}")
        one = back.agg(F.count("*").alias("n"), F.sum(F.col("id") * 31 + F.col("row")).alias("checksum")).select(F.lit(fmt).alias("format"), "n", "checksum")
        out = one if out is None else out.unionByName(one)
    return out


# ---- filters ------------------------------------------------------------------------------------


@query("flt_day_split", f"WITH {EVENTS_SQL} SELECT CASE WHEN day BETWEEN 1 AND 7 THEN 'teacher' ELSE 'eval' END AS split, count(*) AS n FROM ev WHERE day BETWEEN 1 AND 8 GROUP BY ALL")
def flt_day_split(spark, sf_dir):
    e = event_samples(spark, sf_dir).where(F.col("day").between(1, 8))
    return e.groupBy(F.when(F.col("day") <= 7, "teacher").otherwise("eval").alias("split")).agg(F.count("*").alias("n"))


@query("flt_heavy_ids", f"WITH {USES_SQL} SELECT word, count(*) AS n FROM uses GROUP BY word HAVING count(*) >= 100")
def flt_heavy_ids(spark, sf_dir):
    return word_uses(spark, sf_dir).groupBy("word").agg(F.count("*").alias("n")).where("n >= 100")


@query("flt_isin_vocab", "SELECT l_partkey AS id, count(*) AS n FROM lineitem WHERE l_partkey IN (1, 2, 3, 5, 8, 13, 21, 34, 55, 89) GROUP BY 1")
def flt_isin_vocab(spark, sf_dir):
    return table(spark, sf_dir, "lineitem").where(F.col("l_partkey").isin(1, 2, 3, 5, 8, 13, 21, 34, 55, 89)).groupBy(F.col("l_partkey").alias("id")).agg(F.count("*").alias("n"))


@query("flt_null_safe", "SELECT doc_id, l.quality IS NOT DISTINCT FROM 1 AS good FROM documents LEFT JOIN labels l USING (doc_id)")
def flt_null_safe(spark, sf_dir):
    docs, labels = table(spark, sf_dir, "documents").select("doc_id"), table(spark, sf_dir, "labels").select("doc_id", "quality")
    return docs.join(labels, "doc_id", "left").select("doc_id", F.col("quality").eqNullSafe(F.lit(1)).alias("good"))


# ---- joins --------------------------------------------------------------------------------------

_LOOKUP_SQL = "SELECT l_partkey % 97 AS row, count(*) AS uses FROM lineitem GROUP BY 1"


def _part_lookup(spark, sf_dir, how):
    ids = table(spark, sf_dir, "lineitem").select(F.lit("part").alias("feature"), F.col("l_partkey").alias("id"))
    vocab = table(spark, sf_dir, "part").select(F.lit("part").alias("feature"), F.col("p_partkey").alias("id"))
    return mapping.apply(ids, baselines.modulo(vocab, 97), how=how).groupBy("row").agg(F.count("*").alias("uses"))


for _name, _how in (("join_lookup_broadcast", "broadcast"), ("join_lookup_shuffle", "merge"), ("join_lookup_hash", "shuffle_hash"), ("join_lookup_auto", "auto")):
    query(_name, _LOOKUP_SQL)(lambda spark, sf_dir, how=_how: _part_lookup(spark, sf_dir, how))


@query("join_range_cuts", "SELECT p_partkey AS id, floor((p_partkey - 1) / 50.0)::BIGINT AS row FROM part")
def join_range_cuts(spark, sf_dir):
    """Positions to the interval they lie in, as an interval join with broadcast cuts."""
    part = table(spark, sf_dir, "part")
    cuts = part.groupBy(F.floor((F.col("p_partkey") - 1) / 50).alias("row")).agg(F.min("p_partkey").alias("lo_pos"), F.max("p_partkey").alias("hi_pos"))
    cuts = cuts.select(F.lit("part").alias("feature"), F.lit(0).alias("dim"), "row", "lo_pos", "hi_pos")
    chain = part.select(F.lit("part").alias("feature"), F.lit(0).alias("dim"), F.col("p_partkey").alias("pos"), F.col("p_partkey").alias("id"))
    return mapping.emit_range_join(chain, cuts).select("id", "row")


@query("join_outer_vocab", "SELECT p_partkey AS id, count(l_partkey) AS accesses FROM part LEFT JOIN lineitem ON p_partkey = l_partkey GROUP BY 1")
def join_outer_vocab(spark, sf_dir):
    lines = table(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("sample_id"), F.col("l_partkey").alias("part"))
    vocab = table(spark, sf_dir, "part").select(F.lit("part").alias("feature"), F.col("p_partkey").alias("id"))
    return access.count(lines, features=["part"], vocab=vocab).select("id", "accesses")


@query("join_full_drift", f"WITH {EVENTS_SQL}, a AS (SELECT user_id, count(*) AS n FROM ev WHERE day BETWEEN 1 AND 7 GROUP BY 1), b AS (SELECT user_id, count(*) AS n FROM ev WHERE day BETWEEN 8 AND 14 GROUP BY 1) SELECT coalesce(a.user_id, b.user_id) AS id, coalesce(a.n, 0) AS before, coalesce(b.n, 0) AS after FROM a FULL JOIN b ON a.user_id = b.user_id")
def join_full_drift(spark, sf_dir):
    e = event_samples(spark, sf_dir)
    side = lambda lo, hi, name: e.where(F.col("day").between(lo, hi)).groupBy(F.col("user_id").alias("id")).agg(F.count("*").alias(name))
    return side(1, 7, "before").join(side(8, 14, "after"), "id", "full").select("id", F.coalesce("before", F.lit(0)).alias("before"), F.coalesce("after", F.lit(0)).alias("after"))


@query("join_asof_map_version", f"WITH {EVENTS_SQL}, v AS (SELECT * FROM (VALUES (1, 'v1'), (4, 'v2'), (9, 'v3')) t(from_day, version)) SELECT sample_id, (SELECT max_by(version, from_day) FROM v WHERE from_day <= day) AS version FROM ev WHERE day >= 1")
def join_asof_map_version(spark, sf_dir):
    """The map version in force on a sample's day: versions and samples in one ordered pass per user."""
    e = event_samples(spark, sf_dir).where("day >= 1").select("sample_id", "user_id", "day", F.lit(None).cast("string").alias("v"), F.lit(1).alias("kind"))
    versions = F.array(*[F.struct(F.lit(d).alias("day"), F.lit(v).alias("v")) for d, v in ((1, "v1"), (4, "v2"), (9, "v3"))])
    marks = e.select("user_id").distinct().select("user_id", F.explode(versions).alias("m")).select(F.lit(None).cast("long").alias("sample_id"), "user_id", F.col("m.day").alias("day"), F.col("m.v").alias("v"), F.lit(0).alias("kind"))
    w = W.partitionBy("user_id").orderBy("day", "kind").rowsBetween(W.unboundedPreceding, W.currentRow)
    return e.unionByName(marks).withColumn("version", F.last("v", ignorenulls=True).over(w)).where("kind = 1").select("sample_id", "version")


@query("join_interval_sessions", "SELECT a.event_id AS click_id, count(b.event_id) AS purchases FROM events a LEFT JOIN events b ON a.user_id = b.user_id AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR WHERE a.event_type = 'click' GROUP BY 1")
def join_interval_sessions(spark, sf_dir):
    """Purchases within the hour after a click, as an equi-join on (user, hour bucket) and a filter."""
    e = table(spark, sf_dir, "events").select("event_id", "user_id", "event_type", F.col("ts").cast("timestamp").alias("ts"))
    hour = F.floor(F.unix_micros("ts") / 3_600_000_000)
    a = e.where("event_type = 'click'").select(F.col("event_id").alias("click_id"), "user_id", F.col("ts").alias("t"), F.explode(F.array(hour, hour + 1)).alias("hour"))
    b = e.where("event_type = 'purchase'").select("event_id", "user_id", "ts", hour.alias("hour"))
    hits = a.join(b, ["user_id", "hour"]).where("ts >= t AND ts <= t + INTERVAL 1 HOUR").groupBy("click_id").agg(F.count("*").alias("n"))
    return e.where("event_type = 'click'").select(F.col("event_id").alias("click_id")).join(hits, "click_id", "left").select("click_id", F.coalesce("n", F.lit(0)).alias("purchases"))


@query("join_cross_grid", "SELECT priority, returnflag, segment FROM (SELECT DISTINCT o_orderpriority AS priority FROM orders) a CROSS JOIN (SELECT DISTINCT l_returnflag AS returnflag FROM lineitem) b CROSS JOIN (SELECT DISTINCT c_mktsegment AS segment FROM customer) c")
def join_cross_grid(spark, sf_dir):
    """The grid of a workload over cells of order lines: every priority with every return flag and segment, combined or not."""
    kinds = lambda name, column, alias: F.broadcast(table(spark, sf_dir, name).select(F.col(column).alias(alias)).distinct())
    grid = kinds("orders", "o_orderpriority", "priority").crossJoin(kinds("lineitem", "l_returnflag", "returnflag"))
    return grid.crossJoin(kinds("customer", "c_mktsegment", "segment"))


@query("join_salted_hot", f"WITH {VOCAB_SQL} SELECT v.id % 1000 AS row, count(*) AS uses FROM uses u JOIN vocab v ON u.word = v.word GROUP BY 1")
def join_salted_hot(spark, sf_dir):
    """Word uses through a modulo map, hot words salted over copies of their entries."""
    uses = word_uses(spark, sf_dir)
    vocab = word_vocabulary(uses)
    ids = uses.join(vocab.select("word", "id"), "word").select(F.lit("word").alias("feature"), "id", "doc_id", "place")
    entries = vocab.select(F.lit("word").alias("feature"), "id", "accesses")
    hot = entries.where("accesses >= 1000")
    return mapping.apply_salted(ids, baselines.modulo(entries, 1000), hot=hot).groupBy("row").agg(F.count("*").alias("uses"))


# ---- aggregation --------------------------------------------------------------------------------


@query("agg_access_counts", f"WITH {USES_SQL} SELECT word, count(*) AS accesses FROM uses GROUP BY word")
def agg_access_counts(spark, sf_dir):
    return word_uses(spark, sf_dir).groupBy("word").agg(F.count("*").alias("accesses"))


@query("agg_access_multi_feature", f"WITH {ORDERS_SQL} " + " UNION ALL ".join(f"SELECT '{f}' AS feature, {f}::BIGINT AS id, count(*) AS accesses FROM samples GROUP BY 2" for f in ORDER_FEATURES))
def agg_access_multi_feature(spark, sf_dir):
    """All features of the samples counted in one exchange."""
    return access.count(order_samples(spark, sf_dir), features=ORDER_FEATURES)


@query("agg_access_by_day", f"WITH {EVENTS_SQL} SELECT day, user_id, count(*) AS n FROM ev GROUP BY ALL")
def agg_access_by_day(spark, sf_dir):
    return event_samples(spark, sf_dir).groupBy("day", "user_id").agg(F.count("*").alias("n"))


@query("agg_distinct_ids", f"WITH {EVENTS_SQL} SELECT day, count(DISTINCT user_id) AS users, count(DISTINCT k) AS ks FROM ev GROUP BY day")
def agg_distinct_ids(spark, sf_dir):
    return event_samples(spark, sf_dir).groupBy("day").agg(F.count_distinct("user_id").alias("users"), F.count_distinct("k").alias("ks"))


@query("agg_approx_distinct")
def agg_approx_distinct(spark, sf_dir):
    return word_uses(spark, sf_dir).groupBy("day").agg(F.approx_count_distinct("word", 0.02).alias("words"))


@query("agg_hll_union")
def agg_hll_union(spark, sf_dir):
    """Distinct words per day as sketches, and their union over all days."""
    days = word_uses(spark, sf_dir).groupBy("day").agg(F.hll_sketch_agg("word", 14).alias("s"))
    return days.agg(F.hll_sketch_estimate(F.hll_union_agg("s")).alias("words"))


@query("agg_cms_counts", f"WITH {VOCAB_SQL}, cells AS (SELECT id, accesses, unnest([0, 1, 2, 3]) AS h, unnest([" + ", ".join(universal_sql("id", 4096, s) for s in range(4)) + """]) AS cell FROM vocab),
sums AS (SELECT h, cell, sum(accesses) AS total FROM cells GROUP BY ALL) SELECT id, accesses, min(total)::BIGINT AS estimate FROM cells JOIN sums USING (h, cell) GROUP BY ALL""")
def agg_cms_counts(spark, sf_dir):
    """Count-min estimates from array-indexed cells: rows of 4 universal hashes, never under the truth."""
    vocab = word_vocabulary(word_uses(spark, sf_dir)).select("id", "accesses")
    cells = vocab.select("id", "accesses", F.explode(F.array(*[F.struct(F.lit(s).alias("h"), universal(F.col("id"), 4096, s).alias("cell")) for s in range(4)])).alias("c")).select("id", "accesses", "c.*")
    sums = cells.groupBy("h", "cell").agg(F.sum("accesses").alias("total"))
    return cells.join(sums, ["h", "cell"]).groupBy("id", "accesses").agg(F.min("total").alias("estimate"))


@query("agg_cube_split_label", f"WITH {EVENTS_SQL} SELECT CASE WHEN day <= 7 THEN 'teacher' WHEN day = 8 THEN 'eval' ELSE 'later' END AS split, label, count(*) AS n FROM ev GROUP BY CUBE (1, 2)")
def agg_cube_split_label(spark, sf_dir):
    e = event_samples(spark, sf_dir).withColumn("split", F.when(F.col("day") <= 7, "teacher").when(F.col("day") == 8, "eval").otherwise("later"))
    return e.cube("split", "label").agg(F.count("*").alias("n"))


@query("agg_rollup_day_feature", f"WITH {EVENTS_SQL} SELECT day, event_type, count(*) AS n FROM ev GROUP BY ROLLUP (day, event_type)")
def agg_rollup_day_feature(spark, sf_dir):
    return event_samples(spark, sf_dir).rollup("day", "event_type").agg(F.count("*").alias("n"))


@query("agg_gsets_method_size", f"WITH {ORDERS_SQL} SELECT day, segment, priority, count(*) AS n FROM samples GROUP BY GROUPING SETS ((day, segment), (day, priority), ())")
def agg_gsets_method_size(spark, sf_dir):
    s = order_samples(spark, sf_dir)
    return s.groupingSets([["day", "segment"], ["day", "priority"], []], "day", "segment", "priority").agg(F.count("*").alias("n")).select("day", "segment", "priority", "n")


@query("agg_pivot_label", f"WITH {ORDERS_SQL} SELECT day, count(*) FILTER (planted = 0) AS zeros, count(*) FILTER (planted = 1) AS ones FROM samples GROUP BY day")
def agg_pivot_label(spark, sf_dir):
    p = order_samples(spark, sf_dir).groupBy("day").pivot("planted", [0, 1]).count()
    return p.select("day", F.coalesce("0", F.lit(0)).alias("zeros"), F.coalesce("1", F.lit(0)).alias("ones"))


@query("agg_l2_norm", f"WITH {CHAIN_SQL} SELECT round(sqrt(sum(accesses * accesses)::DOUBLE), 6) AS norm FROM chain")
def agg_l2_norm(spark, sf_dir):
    return word_teacher(spark, sf_dir).agg(F.round(F.sqrt(F.sum(F.col("accesses").cast("double") * F.col("accesses"))), 6).alias("norm"))


@query("agg_max_by", f"WITH {EVENTS_SQL} SELECT user_id, max_by(sample_id, (ts, sample_id)) AS last_event FROM ev GROUP BY 1")
def agg_max_by(spark, sf_dir):
    return event_samples(spark, sf_dir).groupBy("user_id").agg(F.max_by("sample_id", F.struct("ts", "sample_id")).alias("last_event"))


@query("agg_vector_sum", "SELECT label, k, round(sum(x::DOUBLE), 6) AS x FROM (SELECT label, unnest(range(64)) AS k, unnest(embedding) AS x FROM embeddings) GROUP BY ALL")
def agg_vector_sum(spark, sf_dir):
    e = table(spark, sf_dir, "embeddings").select("label", F.posexplode("embedding").alias("k", "x"))
    return e.groupBy("label", F.col("k").cast("long").alias("k")).agg(F.round(F.sum(F.col("x").cast("double")), 6).alias("x"))


# ---- windows ------------------------------------------------------------------------------------

_PART_COUNTS = "pc AS (SELECT l_partkey AS id, count(*) AS n FROM lineitem GROUP BY 1), pb AS (SELECT p_brand AS brand, id, n FROM pc JOIN part ON p_partkey = id)"


def _part_counts(spark, sf_dir):
    n = table(spark, sf_dir, "lineitem").groupBy(F.col("l_partkey").alias("id")).agg(F.count("*").alias("n"))
    return n.join(table(spark, sf_dir, "part").select(F.col("p_partkey").alias("id"), F.col("p_brand").alias("brand")), "id")


def _win(name, sql, column):
    @query(name, f"WITH {_PART_COUNTS} SELECT brand, id, {sql} AS x FROM pb")
    def run(spark, sf_dir):
        return _part_counts(spark, sf_dir).select("brand", "id", column().alias("x"))


_by = lambda: W.partitionBy("brand").orderBy("n", "id")
_win("win_chain_lead_gap", "lead(n) OVER (PARTITION BY brand ORDER BY n, id) - n", lambda: F.lead("n").over(_by()) - F.col("n"))
_win("win_rarity_rank", "row_number() OVER (PARTITION BY brand ORDER BY n, id)", lambda: F.row_number().over(_by()))
_win("win_ntile_fold", "ntile(4) OVER (PARTITION BY brand ORDER BY n, id)", lambda: F.ntile(4).over(_by()))
_win("win_percent_rank", "round(percent_rank() OVER (PARTITION BY brand ORDER BY n, id), 6)", lambda: F.round(F.percent_rank().over(_by()), 6))
_win("win_cume_access_share", "round(sum(n) OVER (PARTITION BY brand ORDER BY n, id) / sum(n) OVER (PARTITION BY brand), 6)", lambda: F.round(F.sum("n").over(_by()) / F.sum("n").over(W.partitionBy("brand")), 6))
_win("win_first_last", "last_value(id) OVER (PARTITION BY brand ORDER BY n, id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) * 100000 + first_value(id) OVER (PARTITION BY brand ORDER BY n, id)", lambda: F.last("id").over(_by().rowsBetween(W.unboundedPreceding, W.unboundedFollowing)) * 100000 + F.first("id").over(_by()))


@query("win_gate_topk", f"WITH {_PART_COUNTS} SELECT brand, id, n FROM (SELECT *, row_number() OVER (PARTITION BY brand ORDER BY n DESC, id) AS r FROM pb) WHERE r <= 5")
def win_gate_topk(spark, sf_dir):
    w = W.partitionBy("brand").orderBy(F.desc("n"), "id")
    return _part_counts(spark, sf_dir).withColumn("r", F.row_number().over(w)).where("r <= 5").select("brand", "id", "n")


@query("win_run_islands", "SELECT k - rn AS island, min(k) AS lo, max(k) AS hi, count(*) AS n FROM (SELECT k, row_number() OVER (ORDER BY k) AS rn FROM (SELECT DISTINCT l_partkey AS k FROM lineitem WHERE l_quantity > 45 AND l_discount > 0.07)) GROUP BY 1")
def win_run_islands(spark, sf_dir):
    """Runs of consecutive part ids: gaps and islands over positions from one range exchange."""
    from idfold.plans.ordering import with_positions

    keys = table(spark, sf_dir, "lineitem").where("l_quantity > 45 and l_discount > 0.07").select(F.col("l_partkey").alias("k")).distinct()
    return with_positions(keys, ["k"]).groupBy((F.col("k") - F.col("pos")).alias("island")).agg(F.min("k").alias("lo"), F.max("k").alias("hi"), F.count("*").alias("n"))


@query("win_moving_7d", "SELECT d::VARCHAR AS d, sum(n) OVER (ORDER BY d RANGE BETWEEN INTERVAL 6 DAY PRECEDING AND CURRENT ROW)::BIGINT AS uses FROM (SELECT ts::DATE AS d, count(*) AS n FROM events GROUP BY 1)")
def win_moving_7d(spark, sf_dir):
    """Uses over the last seven days; the window runs over one row per day."""
    days = table(spark, sf_dir, "events").groupBy(F.to_date("ts").alias("d")).agg(F.count("*").alias("n"))
    w = W.orderBy(F.datediff("d", F.lit("2024-01-01"))).rangeBetween(-6, 0)
    return days.select(F.col("d").cast("string").alias("d"), F.sum("n").over(w).alias("uses"))


@query("win_lag_drift", f"WITH {EVENTS_SQL}, n AS (SELECT user_id, day, count(*) AS n FROM ev GROUP BY ALL) SELECT user_id, day, n - lag(n) OVER (PARTITION BY user_id ORDER BY day) AS delta FROM n")
def win_lag_drift(spark, sf_dir):
    n = event_samples(spark, sf_dir).groupBy("user_id", "day").agg(F.count("*").alias("n"))
    return n.select("user_id", "day", (F.col("n") - F.lag("n").over(W.partitionBy("user_id").orderBy("day"))).alias("delta"))


# ---- sort and top-k -----------------------------------------------------------------------------


@query("top_ids_global", f"WITH {USES_SQL} SELECT word, count(*) AS n FROM uses GROUP BY word ORDER BY n DESC, word LIMIT 100")
def top_ids_global(spark, sf_dir):
    return word_uses(spark, sf_dir).groupBy("word").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "word").limit(100)


@query("top_ids_per_feature", f"WITH {ORDERS_SQL}, c AS (" + " UNION ALL ".join(f"SELECT '{f}' AS feature, {f}::BIGINT AS id, count(*) AS accesses FROM samples GROUP BY 2" for f in ORDER_FEATURES) + ") SELECT feature, id, accesses, nth FROM (SELECT *, row_number() OVER (PARTITION BY feature ORDER BY accesses DESC, id) AS nth FROM c) WHERE nth <= 10")
def top_ids_per_feature(spark, sf_dir):
    return baselines.by_frequency(access.count(order_samples(spark, sf_dir), features=ORDER_FEATURES)).where("nth <= 10")


# ---- set operations -----------------------------------------------------------------------------

_DAYS = f"WITH {EVENTS_SQL}, a AS (SELECT user_id FROM ev WHERE day = 5), b AS (SELECT user_id FROM ev WHERE day = 8) SELECT user_id FROM a {{}} SELECT user_id FROM b"


def _set(name, sql_op, op):
    @query(name, _DAYS.format(sql_op))
    def run(spark, sf_dir):
        e = event_samples(spark, sf_dir)
        return op(e.where("day = 5").select("user_id"), e.where("day = 8").select("user_id"))


_set("set_intersect_days", "INTERSECT", lambda a, b: a.intersect(b))
_set("set_intersect_all", "INTERSECT ALL", lambda a, b: a.intersectAll(b))
_set("set_except_unseen", "EXCEPT", lambda a, b: a.subtract(b))
_set("set_except_all", "EXCEPT ALL", lambda a, b: a.exceptAll(b))
_set("set_union_distinct", "UNION", lambda a, b: a.union(b).distinct())
_set("set_union_all", "UNION ALL", lambda a, b: a.union(b))


# ---- scalar functions ---------------------------------------------------------------------------


@query("fn_tokens", r"SELECT item_id, regexp_extract_all(lower(text), '\p{L}+')[1] AS first_word, len(regexp_extract_all(lower(text), '\p{L}+')) AS words FROM benchmark")
def fn_tokens(spark, sf_dir):
    w = F.regexp_extract_all(F.lower("text"), F.lit(r"\p{L}+"), F.lit(0))
    return table(spark, sf_dir, "benchmark").select("item_id", F.get(w, F.lit(0)).alias("first_word"), F.size(w).cast("long").alias("words"))


@query("fn_host", r"SELECT page_id, regexp_extract(url, '^[a-z]+://([^/?#]*)', 1) AS host, split_part(regexp_extract(url, '^[a-z]+://([^/?#]*)', 1), '.', -1) AS tld FROM pages")
def fn_host(spark, sf_dir):
    host = F.parse_url("url", F.lit("HOST"))
    return table(spark, sf_dir, "pages").select("page_id", host.alias("host"), F.element_at(F.split(host, r"\."), -1).alias("tld"))


@query("fn_weekday_align", f"WITH {EVENTS_SQL} SELECT DISTINCT day, dayname(ts) AS weekday FROM ev WHERE day BETWEEN 1 AND 8")
def fn_weekday_align(spark, sf_dir):
    return event_samples(spark, sf_dir).where("day BETWEEN 1 AND 8").select("day", F.date_format("ts", "EEEE").alias("weekday")).distinct()


@query("fn_day_no", "SELECT event_id, (datediff('day', DATE '2024-01-04', ts::DATE) + 1)::INT AS day FROM events")
def fn_day_no(spark, sf_dir):
    return table(spark, sf_dir, "events").select("event_id", (F.datediff(F.to_date("ts"), F.lit("2024-01-04")) + 1).cast("int").alias("day"))


@query("fn_modulo", "SELECT p_partkey AS id, p_partkey % 13 AS row FROM part")
def fn_modulo(spark, sf_dir):
    return table(spark, sf_dir, "part").select(F.col("p_partkey").alias("id"), F.pmod("p_partkey", F.lit(13)).alias("row"))


@query("fn_universal_hash", f"SELECT p_partkey AS id, {universal_sql('p_partkey', 1000)} AS h0, {universal_sql('p_partkey', 1000, 1)} AS h1 FROM part")
def fn_universal_hash(spark, sf_dir):
    return table(spark, sf_dir, "part").select(F.col("p_partkey").alias("id"), universal(F.col("p_partkey"), 1000).alias("h0"), universal(F.col("p_partkey"), 1000, 1).alias("h1"))


@query("fn_prehash", f"SELECT l_partkey AS id, CASE WHEN l_partkey BETWEEN 0 AND 99 THEN l_partkey ELSE {universal_sql('l_partkey', 100)} END AS inside, count(*) AS n FROM lineitem GROUP BY 1, 2")
def fn_prehash(spark, sf_dir):
    return table(spark, sf_dir, "lineitem").groupBy(F.col("l_partkey").alias("id"), prehash(F.col("l_partkey"), 100).alias("inside")).agg(F.count("*").alias("n"))


@query("fn_bits_needed", "SELECT p_partkey AS rows, greatest(ceil(log2(p_partkey::DOUBLE)), 1)::INT AS bits FROM part")
def fn_bits_needed(spark, sf_dir):
    return table(spark, sf_dir, "part").select(F.col("p_partkey").alias("rows"), bits_needed(F.col("p_partkey")).alias("bits"))


@query("fn_norm_count", "WITH pc AS (SELECT l_partkey AS id, count(*) AS n FROM lineitem GROUP BY 1) SELECT id, round(1 + n / sqrt((SELECT sum(n * n)::DOUBLE FROM pc)), 6) AS q FROM pc")
def fn_norm_count(spark, sf_dir):
    n = table(spark, sf_dir, "lineitem").groupBy(F.col("l_partkey").alias("id")).agg(F.count("*").alias("n"))
    norm = n.agg(F.sqrt(F.sum(F.col("n").cast("double") * F.col("n"))).alias("norm"))
    return n.select("id", F.round(norm_count(F.col("n"), norm.scalar()), 6).alias("q"))


@query("fn_slice_dims", "SELECT vec_id, round(embedding[1]::DOUBLE, 6) AS d1, round(embedding[2]::DOUBLE, 6) AS d2 FROM embeddings")
def fn_slice_dims(spark, sf_dir):
    v = F.slice("embedding", 1, 2)
    return table(spark, sf_dir, "embeddings").select("vec_id", F.round(v[0].cast("double"), 6).alias("d1"), F.round(v[1].cast("double"), 6).alias("d2"))


@query("fn_dot", "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE)), 6) AS norm2 FROM embeddings")
def fn_dot(spark, sf_dir):
    return table(spark, sf_dir, "embeddings").select("vec_id", F.round(dot(F.col("embedding"), F.col("embedding")), 6).alias("norm2"))


@query("fn_combine_sum", "SELECT vec_id, round(embedding[1]::DOUBLE + embedding[3]::DOUBLE, 6) AS s1, round(embedding[2]::DOUBLE + embedding[4]::DOUBLE, 6) AS s2 FROM embeddings")
def fn_combine_sum(spark, sf_dir):
    d = F.transform("embedding", lambda x: x.cast("double"))
    s = combine([F.slice(d, 1, 2), F.slice(d, 3, 2)], "sum")
    return table(spark, sf_dir, "embeddings").select("vec_id", F.round(s[0], 6).alias("s1"), F.round(s[1], 6).alias("s2"))


@query("fn_combine_concat", "SELECT vec_id, 4 AS width, round(embedding[4]::DOUBLE, 6) AS last FROM embeddings")
def fn_combine_concat(spark, sf_dir):
    c = combine([F.slice("embedding", 1, 2), F.slice("embedding", 3, 2)], "concat")
    return table(spark, sf_dir, "embeddings").select("vec_id", F.size(c).alias("width"), F.round(c[3].cast("double"), 6).alias("last"))


@query("fn_explode_dims", "SELECT vec_id, unnest([0, 1, 2, 3]) AS dim, round(unnest(embedding[1:4])::DOUBLE, 6) AS value FROM embeddings")
def fn_explode_dims(spark, sf_dir):
    return table(spark, sf_dir, "embeddings").select("vec_id", F.posexplode(F.slice("embedding", 1, 4)).alias("dim", "x")).select("vec_id", "dim", F.round(F.col("x").cast("double"), 6).alias("value"))


@query("fn_feature_map", f"WITH {EVENTS_SQL} SELECT sample_id, user_id AS user, k FROM ev")
def fn_feature_map(spark, sf_dir):
    """Ids of a sample as a map from feature to bag, read back by key."""
    ids = F.map_from_entries(F.array(F.struct(F.lit("user"), F.array("user_id")), F.struct(F.lit("k"), F.array("k"))))
    return event_samples(spark, sf_dir).select("sample_id", ids.alias("ids")).select("sample_id", F.col("ids")["user"][0].alias("user"), F.col("ids")["k"][0].alias("k"))


@query("fn_props_k", "SELECT event_id, (props ->> '$.k')::BIGINT AS k FROM events")
def fn_props_k(spark, sf_dir):
    return table(spark, sf_dir, "events").select("event_id", F.from_json("props", "k bigint")["k"].alias("k"))


# ---- chains, splits and maps as plain queries ---------------------------------------------------


@query("sort_chain", f"WITH {CHAIN_SQL} SELECT pos, id, value, accesses FROM chain")
def sort_chain(spark, sf_dir):
    """The word chain: ids in the order (value, id) with positions, by one range exchange."""
    from idfold.catalog.core import word_chain

    return word_chain(spark, sf_dir).select("pos", "id", F.col("value").cast("long").alias("value"), "accesses")


@query("set_union_maps", f"""WITH {VOCAB_SQL}, ranked AS (SELECT id, row_number() OVER (ORDER BY accesses DESC, id) - 1 AS nth FROM vocab),
kept AS (SELECT id, nth AS row FROM ranked WHERE nth < 100) SELECT id, row FROM kept UNION ALL SELECT id, 100 + id % 900 FROM vocab WHERE id NOT IN (SELECT id FROM kept)""")
def set_union_maps(spark, sf_dir):
    """Private rows for the 100 most used words united with hashed rows behind them for the rest."""
    vocab = word_vocabulary(word_uses(spark, sf_dir)).select(F.lit("word").alias("feature"), "id", "accesses")
    kept = vocab.orderBy(F.desc("accesses"), "id").limit(100).agg(F.collect_list("id").alias("ids")).select(F.posexplode("ids").alias("row", "id"))
    rest = vocab.join(F.broadcast(kept.select("id")), "id", "left_anti")
    return kept.select("id", F.col("row").cast("long").alias("row")).unionByName(rest.select("id", (F.pmod("id", F.lit(900)) + 100).alias("row")))


@query("win_split_pairs", f"""WITH {CHAIN_SQL}, link AS (SELECT pos, lead(value) OVER (ORDER BY pos) - value AS gap FROM chain), zero AS (SELECT pos, pos - row_number() OVER (ORDER BY pos) AS run FROM link WHERE gap = 0)
SELECT pos, run, nth, nth % 2 = 1 AS stays FROM (SELECT pos, run, row_number() OVER (PARTITION BY run ORDER BY pos) AS nth FROM zero)""")
def win_split_pairs(spark, sf_dir):
    """Runs of links without a gap, and every other link of each run that a split keeps."""
    from idfold.catalog.core import word_chain
    from idfold.operators import chain

    zero = chain.links(word_chain(spark, sf_dir)).where("gap = 0").withColumn("run", F.col("pos") - F.row_number().over(W.partitionBy("feature", "dim").orderBy("pos")))
    nth = F.row_number().over(W.partitionBy("run").orderBy("pos"))
    return zero.select("pos", "run", nth.cast("long").alias("nth")).withColumn("stays", F.col("nth") % 2 == 1)


@query("grad_expansion_sum", f"""WITH {ORDERS_SQL}, g AS (SELECT part, unnest([0, 1]) AS slot, 2 * planted - 1 AS a, day AS b FROM samples)
SELECT slot, CASE WHEN slot = 0 THEN part % 50 ELSE part // 50 END AS row, sum(a)::BIGINT AS g0, sum(b)::BIGINT AS g1 FROM g GROUP BY 1, 2""")
def grad_expansion_sum(spark, sf_dir):
    """Gradients of two summed internal tables: all of a sample's gradient goes to the row of each slot."""
    g = order_samples(spark, sf_dir).select(F.col("part").alias("id"), F.lit("part").alias("feature"), F.array(2 * F.col("planted") - 1, F.col("day")).alias("grad"))
    return mapping.expand_gradients(g, _two_part_maps(spark, sf_dir), slots=2, width=2, combine="sum").select("slot", "row", F.col("grad")[0].alias("g0"), F.col("grad")[1].alias("g1"))


@query("grad_expansion_concat", f"""WITH {ORDERS_SQL} SELECT 0 AS slot, part % 50 AS row, sum(2 * planted - 1)::BIGINT AS g0 FROM samples GROUP BY 2
UNION ALL SELECT 1, part // 50, sum(day)::BIGINT FROM samples GROUP BY 2""")
def grad_expansion_concat(spark, sf_dir):
    """Gradients of two concatenated internal tables: each slot gets its slice."""
    g = order_samples(spark, sf_dir).select(F.col("part").alias("id"), F.lit("part").alias("feature"), F.array(2 * F.col("planted") - 1, F.col("day")).alias("grad"))
    return mapping.expand_gradients(g, _two_part_maps(spark, sf_dir), slots=2, width=2, combine="concat").select("slot", "row", F.col("grad")[0].alias("g0"))


def _two_part_maps(spark, sf_dir):
    """Quotient and remainder of the part id as two maps."""
    ids = table(spark, sf_dir, "part").select(F.lit("part").alias("feature"), F.col("p_partkey").alias("id"))
    low = ids.select("feature", F.lit(0).alias("slot"), "id", (F.col("id") % 50).alias("row"))
    return low.unionByName(ids.select("feature", F.lit(1).alias("slot"), "id", F.floor(F.col("id") / 50).alias("row")))
