"""Baselines, measures, teachers and budgets as queries."""

from __future__ import annotations

from pyspark.sql import functions as F

from idfold.catalog.core import params_for, table_teacher, word_chain
from idfold.catalog.registry import CHAIN_SQL, ORDERS_SQL, USES_SQL, VOCAB_SQL, query
from idfold.functions.hashing import universal_sql
from idfold.functions.vectors import quantize
from idfold.operators import baselines, chain, mapping, metrics, teacher
from idfold.sources.samples import event_samples, order_samples, table, word_samples, word_uses, word_vocabulary
from idfold.storage import settle

ROWS = 1000  # rows of the baselines' tables; no multiple of 97, see the planted label


def _words(spark, sf_dir):
    return word_vocabulary(word_uses(spark, sf_dir)).withColumn("feature", F.lit("word"))


def _chain_values(spark, sf_dir):
    return word_chain(spark, sf_dir).select("feature", "id", "value", "accesses")


def _map(df):
    return df.select("slot", "id", "row")


def _base(name, row_sql, make, slot=0):
    @query(name, f"WITH {VOCAB_SQL} SELECT {slot} AS slot, id, ({row_sql})::BIGINT AS row FROM vocab")
    def run(spark, sf_dir):
        return _map(make(_words(spark, sf_dir)))


_base("base_identity", "id", baselines.identity)
_base("base_modulo", f"id % {ROWS}", lambda v: baselines.modulo(v, ROWS))
_base("base_hash", universal_sql("id", ROWS), lambda v: baselines.hashed(v, ROWS))
_base("base_truncate", f"least(row_number() OVER (ORDER BY accesses DESC, id), {ROWS}) - 1", lambda v: baselines.truncate(v, ROWS))


@query("base_two_hash", f"WITH {VOCAB_SQL} SELECT 0 AS slot, id, {universal_sql('id', ROWS)} AS row FROM vocab UNION ALL SELECT 1, id, {universal_sql('id', ROWS, 1)} FROM vocab")
def base_two_hash(spark, sf_dir):
    return _map(baselines.hashed(_words(spark, sf_dir), ROWS, slots=2))


@query("base_quotient_remainder", f"WITH {VOCAB_SQL} SELECT 0 AS slot, id, id % {ROWS} AS row FROM vocab UNION ALL SELECT 1, id, id // {ROWS} FROM vocab")
def base_quotient_remainder(spark, sf_dir):
    return _map(baselines.quotient_remainder(_words(spark, sf_dir), ROWS))


_RANKED = "ranked AS (SELECT *, row_number() OVER (ORDER BY accesses DESC, id) AS nth, ceil(count(*) OVER () * 1.0 / 100.0)::BIGINT AS kept FROM vocab)"


@query("base_retain_double_hash", f"WITH {VOCAB_SQL}, {_RANKED} SELECT 0 AS slot, id, CASE WHEN nth <= kept THEN nth - 1 ELSE kept + {universal_sql('id', '(5000 - kept)')} END AS row FROM ranked UNION ALL SELECT 1, id, {universal_sql('id', 5000, 1)} FROM ranked WHERE nth > kept")
def base_retain_double_hash(spark, sf_dir):
    """1 % of the words keep private rows; the others two hashed rows in internal tables of 5000."""
    return _map(baselines.retain_double_hash(_words(spark, sf_dir), 5000, 1.0))


@query("base_retain_learned")
def base_retain_learned(spark, sf_dir):
    """1 % of the words keep private rows, the rest share learned rows behind them (10 % in all)."""
    t = settle(_chain_values(spark, sf_dir))
    n, kept = t.count(), settle(baselines.kept_rows(t, 1.0))
    room = max(1, -(-n // 10) - kept.count())
    rest = t.join(kept.select("feature", "id"), ["feature", "id"], "left_anti").select("feature", "id", F.array("value").alias("vec"), "accesses")
    c = settle(chain.build(rest))
    p = params_for(c.count(), gates=("rarity", "gap", "bulk"), value_rule="count_weighted")
    folded = mapping.emit(c, chain.fold_local(c, type(p)(**{**p.__dict__, "row_budget": room})))
    return _map(mapping.retain(t, folded, kept=kept))


@query("base_attribute", "SELECT 0 AS slot, p_partkey AS id, dense_rank() OVER (ORDER BY p_brand) - 1 AS row FROM part")
def base_attribute(spark, sf_dir):
    v = table(spark, sf_dir, "part").select(F.lit("part").alias("feature"), F.col("p_partkey").alias("id"), "p_brand")
    return _map(baselines.attribute(v, "p_brand"))


@query("base_quantile", f"WITH {CHAIN_SQL} SELECT 0 AS slot, id, ntile({ROWS}) OVER (ORDER BY value, id) - 1 AS row FROM chain")
def base_quantile(spark, sf_dir):
    return _map(baselines.quantile(_chain_values(spark, sf_dir), ROWS))


@query("base_quantile_access", f"WITH {CHAIN_SQL} SELECT 0 AS slot, id, least((sum(accesses) OVER (ORDER BY value, id) - accesses)::BIGINT * {ROWS} // (sum(accesses) OVER ())::BIGINT, {ROWS - 1})::BIGINT AS row FROM chain")
def base_quantile_access(spark, sf_dir):
    return _map(baselines.quantile_access(_chain_values(spark, sf_dir), ROWS))


@query("base_cooccurrence", """WITH b AS (SELECT DISTINCT l_orderkey AS s, l_partkey % 200 AS id FROM lineitem), n AS (SELECT id, count(*) AS n FROM b GROUP BY id), t AS (SELECT count(DISTINCT s) AS t FROM b),
p AS (SELECT x.id AS a, y.id AS b, count(*) AS together FROM b x JOIN b y ON x.s = y.s AND x.id < y.id GROUP BY ALL HAVING count(*) >= 3)
SELECT p.a, p.b, together, round(ln(together * t / (na.n * nb.n)::DOUBLE), 6) AS pmi FROM p JOIN n na ON na.id = p.a JOIN n nb ON nb.id = p.b, t""")
def base_cooccurrence(spark, sf_dir):
    uses = table(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("sample_id"), (F.col("l_partkey") % 200).alias("id"))
    return baselines.cooccurrence(uses)


@query("base_cooccurrence_ids")
def base_cooccurrence_ids(spark, sf_dir):
    """Pairs of the part ids themselves, which ``base_cooccurrence`` takes modulo 200 as its SQL does."""
    uses = table(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("sample_id"), F.col("l_partkey").alias("id"))
    return baselines.cooccurrence(uses)


# ---- measures -----------------------------------------------------------------------------------

_PLANTED_SCORE = "((part * 37) % 97 - 48 + (customer * 53) % 97 - 48)"


def _scored(spark, sf_dir):
    s = order_samples(spark, sf_dir)
    return s.select("day", F.col("planted").alias("label"), ((F.col("part") * 37) % 97 - 48 + (F.col("customer") * 53) % 97 - 48).alias("score"))


_AUC = """per AS (SELECT {keys} s, sum(CASE WHEN label = 1 THEN 1 ELSE 0 END)::DOUBLE AS a, sum(CASE WHEN label = 0 THEN 1 ELSE 0 END)::DOUBLE AS b FROM scored GROUP BY ALL),
won AS (SELECT *, a * (coalesce(sum(b) OVER ({part} ORDER BY s ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) + b / 2) AS won FROM per)
SELECT {keys} sum(a)::BIGINT AS positives, sum(b)::BIGINT AS negatives, round(sum(won) / (sum(a) * sum(b)), 6) AS auc FROM won GROUP BY ALL"""


@query("auc_exact", f"WITH {ORDERS_SQL}, scored AS (SELECT planted AS label, {_PLANTED_SCORE} AS s FROM samples), " + _AUC.format(keys="", part=""))
def auc_exact(spark, sf_dir):
    """AUC of the hidden scores against the planted label: the ceiling for any model."""
    return metrics.auc(_scored(spark, sf_dir))


@query("auc_by_day", f"WITH {ORDERS_SQL}, scored AS (SELECT day, planted AS label, {_PLANTED_SCORE} AS s FROM samples), " + _AUC.format(keys="day,", part="PARTITION BY day"))
def auc_by_day(spark, sf_dir):
    return metrics.auc(_scored(spark, sf_dir), keys=["day"])


@query("auc_mean_reps", f"WITH {ORDERS_SQL}, scored AS (SELECT day, planted AS label, {_PLANTED_SCORE} AS s FROM samples), r AS (WITH " + _AUC.format(keys="day,", part="PARTITION BY day") + ") SELECT round(avg(auc), 6) AS mean_auc, min(auc) AS min_auc, max(auc) AS max_auc, count(*) AS reps FROM r")
def auc_mean_reps(spark, sf_dir):
    """Mean and spread over repetitions (here the eight days)."""
    return metrics.mean_reps(metrics.auc(_scored(spark, sf_dir), keys=["day"]), keys=[])


@query("logloss", f"WITH {ORDERS_SQL}, p AS (SELECT planted AS label, 1 / (1 + exp(-({_PLANTED_SCORE}) / 60.0)) AS p FROM samples) SELECT round(avg(CASE WHEN label = 1 THEN -ln(p) ELSE -ln(1 - p) END), 6) AS logloss, round(avg(p) / avg(label), 6) AS calibration FROM p")
def logloss(spark, sf_dir):
    s = _scored(spark, sf_dir).select("label", (1 / (1 + F.exp(-F.col("score") / 60.0))).alias("score"))
    return metrics.log_loss(s)


_LOADS = f"m AS (SELECT id, id % {ROWS} AS row, accesses, fr_uses FROM vocab), loads AS (SELECT row, count(*) AS z, sum(accesses)::BIGINT AS c, sum(accesses * accesses)::BIGINT AS c2 FROM m GROUP BY row)"


@query("collision_report", f"WITH {VOCAB_SQL}, {_LOADS} SELECT sum(z)::BIGINT AS ids, count(*) AS rows_used, (sum(z) - count(*))::BIGINT AS collisions, sum(z * (z - 1) // 2)::BIGINT AS id_pairs, sum((c::HUGEINT * c - c2) // 2)::BIGINT AS use_pairs FROM loads")
def collision_report(spark, sf_dir):
    w = settle(_words(spark, sf_dir))
    return metrics.collisions(baselines.modulo(w, ROWS), w).select("ids", "rows_used", "collisions", "id_pairs", "use_pairs")


@query("row_load_report", f"WITH {VOCAB_SQL}, {_LOADS} SELECT max(z) AS max_load, quantile_cont(z, 0.99) AS p99_load, round(avg(CASE WHEN z >= 69 THEN 1.0 ELSE 0.0 END), 6) AS at_cap FROM loads")
def row_load_report(spark, sf_dir):
    w = settle(_words(spark, sf_dir))
    return metrics.load_report(baselines.modulo(w, ROWS), w, cap=69).select("max_load", "p99_load", "at_cap")


@query("purity_report", f"WITH {VOCAB_SQL}, {_LOADS} SELECT sum(accesses)::BIGINT AS uses, round(sum(greatest(fr, accesses - fr)) / sum(accesses), 6) AS purity FROM (SELECT row, sum(accesses) AS accesses, sum(fr_uses) AS fr FROM m GROUP BY row)")
def purity_report(spark, sf_dir):
    w = settle(_words(spark, sf_dir))
    classes = F.array(F.struct(F.lit("fr").alias("class"), F.col("fr_uses").alias("n")), F.struct(F.lit("other").alias("class"), (F.col("accesses") - F.col("fr_uses")).alias("n")))
    uses = w.select("feature", "id", F.explode(classes).alias("u")).select("feature", "id", "u.*")
    return metrics.purity(baselines.modulo(w, ROWS), uses).select("uses", "purity")


@query("variance_report", f"WITH {CHAIN_SQL}, r AS (SELECT sum(accesses)::DOUBLE AS c, sum(accesses * value)::DOUBLE AS s, sum((accesses * value)::HUGEINT * value)::DOUBLE AS q FROM chain GROUP BY id % {ROWS}) SELECT round(sum(q - s * s / c) / sum(c) / 1e6) AS variance_millions FROM r")
def variance_report(spark, sf_dir):
    t = settle(_chain_values(spark, sf_dir).withColumn("value", F.col("value").cast("double")))
    return metrics.within_row_variance(baselines.modulo(t, ROWS), t).select(F.round(F.col("variance") / 1e6).alias("variance_millions"))


@query("skew_report", f"""WITH {VOCAB_SQL}, r AS (SELECT accesses AS c, row_number() OVER (ORDER BY accesses) AS up, row_number() OVER (ORDER BY accesses DESC) AS down FROM vocab)
SELECT count(*) AS ids, sum(c)::BIGINT AS uses, count(*) FILTER (c = 1) AS once, round(sum(c) FILTER (down <= 100) / sum(c), 6) AS top_share, round(2.0 * sum(up * c)::DOUBLE / (count(*) * sum(c)::DOUBLE) - (count(*) + 1.0) / count(*), 6) AS gini FROM r""")
def skew_report(spark, sf_dir):
    return metrics.skew(_words(spark, sf_dir)).select("ids", "uses", "once", "top_share", "gini")


@query("map_memory", f"WITH {VOCAB_SQL} SELECT count(*) AS entries, {ROWS}::BIGINT AS tallest, 10 AS bits, ceil(count(*) * 10 / 8.0)::BIGINT AS bytes FROM vocab")
def map_memory(spark, sf_dir):
    return mapping.map_memory(baselines.modulo(_words(spark, sf_dir), ROWS))


_HEIGHTS = "SELECT 'part' AS feature, count(*) AS height FROM part UNION ALL SELECT 'supplier', count(*) FROM supplier UNION ALL SELECT 'customer', count(*) FROM customer UNION ALL SELECT 'nation', count(*) FROM nation UNION ALL SELECT 'region', count(*) FROM region UNION ALL SELECT 'user', count(DISTINCT user_id) FROM events"


def heights(spark, sf_dir):
    out = None
    for name in ("part", "supplier", "customer", "nation", "region"):
        one = table(spark, sf_dir, name).agg(F.count("*").alias("height")).select(F.lit(name).alias("feature"), "height")
        out = one if out is None else out.unionByName(one)
    return out.unionByName(table(spark, sf_dir, "events").agg(F.count_distinct("user_id").alias("height")).select(F.lit("user").alias("feature"), "height"))


_PLAN = f"plan AS (SELECT feature, height, height >= 1000 AS folded, CASE WHEN height >= 1000 THEN greatest(greatest(ceil(height * 10 / 100.0), 1) // 2, 1) ELSE height END::BIGINT AS rows_per_slot FROM ({_HEIGHTS}))"


@query("size_plan_skip", f"WITH {_PLAN} SELECT *, CASE WHEN folded THEN rows_per_slot * 2 ELSE rows_per_slot END AS total_rows FROM plan")
def size_plan_skip(spark, sf_dir):
    """Rows per table at 10 % with two slots sharing the budget; tables under 1000 rows stay whole."""
    return mapping.plan(heights(spark, sf_dir), size_pct=10, skip_below=1000, slots=2)


@query("size_report", f"WITH {_PLAN} SELECT sum(height * 16)::BIGINT AS full_params, sum((CASE WHEN folded THEN rows_per_slot * 2 ELSE rows_per_slot END) * 8)::BIGINT AS folded_params, round(100.0 * sum((CASE WHEN folded THEN rows_per_slot * 2 ELSE rows_per_slot END) * 8 * 8) / sum(height * 16 * 32), 6) AS size_pct FROM plan")
def size_report(spark, sf_dir):
    """Folding composed with half the width and 8-bit entries."""
    return mapping.size_report(mapping.plan(heights(spark, sf_dir), size_pct=10, skip_below=1000, slots=2), width=8, bits=8)


@query("agg_heights_quartiles", f"SELECT count(*) AS tables, max(height) AS max_height, quantile_cont(height, 0.25) AS p25, quantile_cont(height, 0.5) AS median, quantile_cont(height, 0.75) AS p75 FROM ({_HEIGHTS})")
def agg_heights_quartiles(spark, sf_dir):
    return metrics.heights_summary(heights(spark, sf_dir))


@query("quantize_report", "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: abs(x::DOUBLE - greatest(least(round(x::DOUBLE * 127 / 0.5), 127), -127) * 0.5 / 127))), 5) AS error FROM embeddings")
def quantize_report(spark, sf_dir):
    """Absolute error per vector of 8-bit entries."""
    v = F.transform("embedding", lambda x: x.cast("double"))
    error = F.aggregate(F.zip_with(v, quantize(v, 8, 0.5), lambda a, b: F.abs(a - b)), F.lit(0.0), lambda s, x: s + x)
    return table(spark, sf_dir, "embeddings").select("vec_id", F.round(error, 5).alias("error"))


# ---- teachers -----------------------------------------------------------------------------------


@query("teach_rate", f"WITH {USES_SQL}, d AS (SELECT * FROM uses WHERE day BETWEEN 1 AND 7), h AS (SELECT word FROM d GROUP BY word ORDER BY count(*) DESC, word LIMIT 100), k AS (SELECT * FROM uses WHERE word NOT IN (SELECT word FROM h)), t AS (SELECT * FROM k WHERE day BETWEEN 1 AND 7), p AS (SELECT avg(fr) AS p FROM t) SELECT word, count(*) AS accesses, round(1e6 * (sum(fr) + any_value(p)) / (count(*) + 1)) AS value FROM t, p GROUP BY word")
def teach_rate(spark, sf_dir):
    """Smoothed French share per word over the teacher's days."""
    samples = word_samples(spark, sf_dir).where("day BETWEEN 1 AND 7")
    names = _words(spark, sf_dir).select("id", "word")
    return teacher.rate(samples, feature="word").join(names, "id").select("word", "accesses", F.col("vec")[0].alias("value"))


@query("teach_table_dims", "SELECT vec_id AS id, round(embedding[1]::DOUBLE, 6) AS d1, round(embedding[2]::DOUBLE, 6) AS d2, round(embedding[3]::DOUBLE, 6) AS d3, round(embedding[4]::DOUBLE, 6) AS d4 FROM embeddings")
def teach_table_dims(spark, sf_dir):
    t = table_teacher(spark, sf_dir)
    return t.select("id", *[F.round(F.col("vec")[k], 6).alias(f"d{k + 1}") for k in range(4)])


@query("teach_als")
def teach_als(spark, sf_dir):
    """Two latent values per part and customer from implicit counts of order lines."""
    return teacher.als(order_samples(spark, sf_dir).select("customer", "part"), user="customer", item="part")


@query("teach_fm")
def teach_fm(spark, sf_dir):
    """Factorisation machine of width 2 over users and k of the events of days 1-7."""
    e = event_samples(spark, sf_dir).where("day BETWEEN 1 AND 7")
    return teacher.fm(e.select("user_id", "k", "label"), features=["user_id", "k"], heights={}, steps=20)


@query("teach_deep")
def teach_deep(spark, sf_dir):
    """Width-2 click model over nation, supplier and part with the planted label, days 1-7."""
    s = order_samples(spark, sf_dir).where("day BETWEEN 1 AND 7").select("nation", "supplier", "part", F.col("planted").alias("label"))
    h = s.agg(*[(F.max(c) + 1).cast("int").alias(c) for c in ("nation", "supplier", "part")]).first()
    return teacher.deep(s, features=["nation", "supplier", "part"], heights=h.asDict())


@query("lookup_two_slots_sum")
def lookup_two_slots_sum(spark, sf_dir):
    """Vectors of word bags through two learned slots, internal tables of row-numbered vectors, summed."""
    return _lookup(spark, sf_dir, "sum")


@query("lookup_two_slots_concat")
def lookup_two_slots_concat(spark, sf_dir):
    return _lookup(spark, sf_dir, "concat")


def _lookup(spark, sf_dir, how):
    c = settle(chain.build(table_teacher(spark, sf_dir, 2)))
    n = c.where("dim = 0").count()
    m = settle(mapping.emit(c, chain.fold_local(c, params_free(n))))
    tables = m.select("feature", "slot", "row").distinct().withColumn("vec", F.array((F.col("row") % 7).cast("double"), (F.col("row") % 11).cast("double")))
    ids = c.where("dim = 0").select((F.col("id") % 100).alias("sample_id"), "feature", "id")
    return mapping.lookup(ids, m, tables, slots=2, combine=how)


def params_free(n: int):
    from idfold.operators.kernel import FoldParams

    return FoldParams(row_budget=max(1, n // 10))


@query("purity_learned_vs_hashing")
def purity_learned_vs_hashing(spark, sf_dir):
    """Does folding avoid bad collisions: a map learned on days 1-7 judged on the uses of day 8."""
    uses = settle(word_uses(spark, sf_dir))
    vocab = settle(word_vocabulary(uses))
    early = uses.where("day BETWEEN 1 AND 7").groupBy("word").agg(F.count("*").alias("accesses"), F.sum("fr").alias("fr"))
    known = vocab.select("id", "word").join(early, "word", "left").select("id", F.coalesce("accesses", F.lit(0)).alias("accesses"), F.coalesce(F.expr("1000000 * fr div accesses"), F.lit(145000)).alias("value"))
    c = settle(chain.build(known.select(F.lit("word").alias("feature"), "id", F.array("value").alias("vec"), "accesses")))
    p = params_for(c.count(), gates=("rarity", "gap", "bulk"), value_rule="count_weighted")
    late = uses.where("day = 8").join(vocab.select("id", "word"), "word").groupBy("id", F.when(F.col("fr") == 1, "fr").otherwise("other").alias("class")).agg(F.count("*").alias("n")).withColumn("feature", F.lit("word"))
    late, out = settle(late), None
    maps = {"learned": mapping.emit(c, chain.fold_local(c, p)), "modulo": baselines.modulo(c, p.row_budget), "random_hash": baselines.hashed(c, p.row_budget), "quantile": baselines.quantile(c, p.row_budget)}
    for name, m in maps.items():
        one = metrics.purity(settle(m), late).withColumn("method", F.lit(name))
        out = one if out is None else out.unionByName(one)
    return out
