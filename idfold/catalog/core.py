"""Queries on the folding method itself: chains, gates, rounds, full folds, maps."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from idfold.catalog.registry import CHAIN_SQL, VOCAB_SQL, query
from idfold.operators import baselines, chain, mapping, metrics, teacher
from idfold.operators.kernel import FREQUENCY_MODES, FoldParams
from idfold.plans.oracles import RoundSql, round_ctes
from idfold.sources.samples import table, word_uses, word_vocabulary
from idfold.storage import settle


def word_teacher(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Exact one-dimensional teacher: share of a word's uses that are French, in whole micro-units."""
    vocab = word_vocabulary(word_uses(spark, sf_dir))
    return vocab.select(F.lit("word").alias("feature"), "id", F.array(F.expr("1000000 * fr_uses div accesses")).alias("vec"), "accesses")


def word_chain(spark: SparkSession, sf_dir: str) -> DataFrame:
    return settle(chain.build(word_teacher(spark, sf_dir)))


def params_for(n: int, *, budget: float = 0.1, stride: float = 0.01, cap: int | None = None, **more) -> FoldParams:
    m = max(1, math.ceil(n * budget))
    return FoldParams(row_budget=m, stride=max(1, math.ceil(n * stride)), size_cap=cap or math.ceil(4 * n / m), micro=True, **more)


def _setup(spark: SparkSession, sf_dir: str, **options) -> tuple[DataFrame, FoldParams]:
    c = word_chain(spark, sf_dir)
    return c, params_for(c.count(), **options)


def _scored(c: DataFrame, p: FoldParams) -> DataFrame:
    return chain.links(c).join(F.broadcast(chain.merges_to_do(c, p)), chain.KEYS)


def _sql(ctes: list[str], tail: str) -> str:
    return f"WITH {CHAIN_SQL}, {', '.join(ctes)} {tail}"


_R1 = round_ctes("chain", "c1", RoundSql())
_ROUND = "SELECT pos, value, size, accesses FROM {}"


@query("chain_words", f"WITH {CHAIN_SQL} SELECT pos, id, value, size, accesses FROM chain")
def chain_words(spark, sf_dir):
    return word_chain(spark, sf_dir).select("pos", "id", "value", "size", "accesses")


@query("fold_round1_links", _sql(_R1, "SELECT pos, round(rarity, 6) AS rarity, gap, bulk FROM c1_links"))
def fold_round1_links(spark, sf_dir):
    c, p = _setup(spark, sf_dir)
    return _scored(c, p).select("pos", F.round("rarity", 6).alias("rarity"), "gap", "bulk")


def _gate(spark, sf_dir, places: int) -> DataFrame:
    c, p = _setup(spark, sf_dir)
    part = FoldParams(**{**p.__dict__, "gates": p.gates[:places], "widths": p.widths[:places]})
    return chain.gate(_scored(c, p), part).select("pos", "gap", "bulk", *[f"rank{k + 1}" for k in range(places)])


@query("fold_round1_rarity", _sql(_R1, "SELECT pos, gap, bulk, rank1 FROM c1_gate1"))
def fold_round1_rarity(spark, sf_dir):
    return _gate(spark, sf_dir, 1)


@query("fold_round1_gap", _sql(_R1, "SELECT pos, gap, bulk, rank1, rank2 FROM c1_gate2"))
def fold_round1_gap(spark, sf_dir):
    return _gate(spark, sf_dir, 2)


@query("fold_round1_bulk", _sql(_R1, "SELECT pos, gap, bulk, rank1, rank2, rank3 FROM c1_gate3"))
def fold_round1_bulk(spark, sf_dir):
    return _gate(spark, sf_dir, 3)


@query("fold_round1_runs", _sql(_R1, "SELECT pos, run_id, in_run, run_size FROM c1_runs"))
def fold_round1_runs(spark, sf_dir):
    c, p = _setup(spark, sf_dir)
    return chain.runs(chain.gate(_scored(c, p), p), c).select("pos", "run_id", "in_run", "run_size")


@query("fold_round1_split", _sql(round_ctes("chain", "c1", RoundSql(cap="3", stride="ceil(n0 / 5.0)::BIGINT")), "SELECT pos FROM c1_stay"))
def fold_round1_split(spark, sf_dir):
    c, p = _setup(spark, sf_dir, stride=0.2, cap=3)
    return chain.split_runs(chain.runs(chain.gate(_scored(c, p), p), c), p).select("pos")


def _rounds(name: str, rounds: int, sql: RoundSql, **options) -> None:
    """Register ``rounds`` rounds of the distributed engine against the unrolled SQL."""
    ctes: list[str] = []
    for k in range(rounds):
        ctes += round_ctes("chain" if k == 0 else f"c{k}", f"c{k + 1}", sql)

    @query(name, _sql(ctes, _ROUND.format(f"c{rounds}")))
    def run(spark, sf_dir):
        c, p = _setup(spark, sf_dir, **options)
        now = c.select("feature", "dim", "pos", "value", "size", "accesses")
        for _ in range(rounds):
            now = settle(chain.step(now, p)[0])
        return now.select("pos", "value", "size", "accesses")


def _mode(name: str) -> dict:
    return FREQUENCY_MODES[name]


_fifth = "ceil(n0 / 5.0)::BIGINT"
_rounds("fold_round1_merged", 1, RoundSql())
_rounds("fold_three_rounds", 3, RoundSql())
_rounds("fold_weighted_round", 1, RoundSql(stride=_fifth, **_mode("weight_and_filter")), stride=0.2, **_mode("weight_and_filter"))
_rounds("fold_weight_only_round", 1, RoundSql(stride=_fifth, **_mode("weight_only")), stride=0.2, **_mode("weight_only"))
_rounds("fold_nofreq_round", 1, RoundSql(stride=_fifth, **_mode("none")), stride=0.2, **_mode("none"))
_rounds("fold_filter_only_round", 1, RoundSql(stride=_fifth, **_mode("filter_only")), stride=0.2, **_mode("filter_only"))
_rounds("fold_reordered_round", 1, RoundSql(stride=_fifth, gates=("bulk", "gap", "rarity")), stride=0.2, gates=("bulk", "gap", "rarity"))
_rounds("fold_single_gate_round", 1, RoundSql(stride=_fifth, gates=("gap",)), stride=0.2, gates=("gap",))
_rounds("fold_fallback_round", 2, RoundSql(stride=_fifth, cap="1"), stride=0.2, cap=1)
_rounds("fold_split_pairs_round", 2, RoundSql(stride=_fifth, cap="3"), stride=0.2, cap=3)
_rounds("fold_strict_round", 1, RoundSql(stride=_fifth, cap="3", strict=True), stride=0.2, cap=3, strict=True)
_rounds("fold_all_fitting_round", 1, RoundSql(stride=_fifth, bulk_limit="all"), stride=0.2, bulk_limit="all")
_rounds("fold_size_weighted_round", 2, RoundSql(stride=_fifth, value_rule="size_weighted"), stride=0.2, value_rule="size_weighted")


@query("fold_full_local")
def fold_full_local(spark, sf_dir):
    """Cuts of the word chain at 10 % of the ids, one task for the chain."""
    c, p = _setup(spark, sf_dir)
    return chain.fold_local(c, p)


@query("fold_quarter_local")
def fold_quarter_local(spark, sf_dir):
    """Cuts at 10 % of the ids in strides of a quarter, one task for the chain."""
    c, p = _setup(spark, sf_dir, stride=0.25)
    return chain.fold_local(c, p)


@query("fold_full_distributed")
def fold_full_distributed(spark, sf_dir):
    """The cuts of ``fold_quarter_local`` from the distributed engine."""
    c, p = _setup(spark, sf_dir, stride=0.25)
    return chain.fold_distributed(c, p)[1]


@query("fold_pack_distributed")
def fold_pack_distributed(spark, sf_dir):
    """``fold_pack_split`` from the distributed engine, for the first three rounds."""
    c, p = _setup(spark, sf_dir, stride=0.2, cap=12, split="pack", max_rounds=3)
    return chain.fold_distributed(c, p)[1]


@query("fold_single_merge_rounds")
def fold_single_merge_rounds(spark, sf_dir):
    """One merge per round (the classic bottom-up case), for the last 50 merges of the rarest tail."""
    c = word_chain(spark, sf_dir)
    n = c.count()
    return chain.fold_local(c, FoldParams(row_budget=max(1, n - 50), stride=1, size_cap=n, gates=("gap",), micro=True))


@query("fold_pack_split")
def fold_pack_split(spark, sf_dir):
    c, p = _setup(spark, sf_dir, stride=0.2, cap=12, split="pack")
    return chain.fold_local(c, p)


@query("fold_trace")
def fold_trace(spark, sf_dir):
    c, p = _setup(spark, sf_dir)
    return chain.fold_trace(c, p)


def word_map(spark, sf_dir, **options) -> tuple[DataFrame, DataFrame]:
    """Learned map of the words and the chain it came from."""
    c, p = _setup(spark, sf_dir, **options)
    return mapping.emit(c, chain.fold_local(c, p)), c


@query("fold_map_words")
def fold_map_words(spark, sf_dir):
    return word_map(spark, sf_dir, **_mode("weight_and_filter"))[0]


@query("fold_map_range_join")
def fold_map_range_join(spark, sf_dir):
    """Emission as an interval join with broadcast cuts, on the 4 first dimensions of a trained table."""
    c = settle(chain.build(table_teacher(spark, sf_dir)))
    n = c.where("dim = 0").count()
    return mapping.emit_range_join(c, chain.fold_local(c, FoldParams(row_budget=max(1, n // 10))))


def table_teacher(spark, sf_dir, dims: int = 4) -> DataFrame:
    """The first dimensions of the given embeddings; use counts of the words of equal frequency rank."""
    words = baselines.by_frequency(word_teacher(spark, sf_dir)).select((F.col("nth") - 1).cast("long").alias("id"), "accesses")
    return teacher.from_table(table(spark, sf_dir, "embeddings"), id_col="vec_id", vec_col="embedding", dims=dims, feature="vector", accesses=words)


@query("fold_two_slots")
def fold_two_slots(spark, sf_dir):
    """Two overlapping groupings, one per latent dimension of a trained table."""
    c = settle(chain.build(table_teacher(spark, sf_dir, 2)))
    n = c.where("dim = 0").count()
    return mapping.emit(c, chain.fold_local(c, FoldParams(row_budget=max(1, n // 10), **_mode("weight_and_filter"))))


@query("fold_frequency_modes")
def fold_frequency_modes(spark, sf_dir):
    """The four ways to use access counts: collisions of uses and purity of each map."""
    c, _ = _setup(spark, sf_dir)
    n, counts = c.count(), c.select("feature", "id", "accesses")
    out = None
    for name, mode in FREQUENCY_MODES.items():
        fold_map = settle(mapping.emit(c, chain.fold_local(c, params_for(n, **mode))))
        one = metrics.collisions(fold_map, counts).withColumn("mode", F.lit(name))
        out = one if out is None else out.unionByName(one)
    return out


@query("fold_gate_orders")
def fold_gate_orders(spark, sf_dir):
    """Six orders of three gates, pairs in both orders, and single gates: rounds, merges, fallbacks, splits."""
    from itertools import permutations

    from idfold.operators.kernel import GATES

    c = settle(chain.build(table_teacher(spark, sf_dir, 1)))
    n, out = c.count(), None
    for k in (3, 2, 1):
        for gates in permutations(GATES, k):
            for rule in ("mean", "count_weighted"):
                t = chain.fold_trace(c, FoldParams(row_budget=max(1, n // 10), stride=max(1, n // 20), gates=gates, value_rule=rule))
                one = t.agg(F.count("*").alias("rounds"), F.sum("merges").alias("merges"), F.sum(F.col("fallback").cast("int")).alias("fallbacks"), F.sum("runs_split").alias("splits"), F.sum("links").alias("links_scored"))
                one = one.select(F.lit(">".join(gates)).alias("gates"), F.lit(rule).alias("value_rule"), "*")
                out = one if out is None else out.unionByName(one)
    return out


@query("map_save_load_relevance", f"""WITH {VOCAB_SQL}, talk AS (SELECT unnest(regexp_extract_all(lower(text), '\\p{{L}}+')) AS word FROM conversations)
SELECT 'word' AS feature, count(*) AS uses, count(*) FILTER (word IN (SELECT word FROM vocab)) AS known_uses, round(1 - count(*) FILTER (word IN (SELECT word FROM vocab)) / count(*), 6) AS unseen_share FROM talk""")
def map_save_load_relevance(spark, sf_dir):
    """A saved and reloaded word map against the words of conversations: share of uses it does not know."""
    import uuid

    from idfold.storage import shared_folder

    vocab = word_vocabulary(word_uses(spark, sf_dir))
    by_id = vocab.select(F.lit("word").alias("feature"), "id")
    path = f"{shared_folder(spark)}/idfold-map-{uuid.uuid4().hex}"
    mapping.save(baselines.modulo(by_id, 1000), path, version="v1")
    loaded = mapping.load(spark, path, version="v1")
    talk = table(spark, sf_dir, "conversations").select(F.explode(F.regexp_extract_all(F.lower("text"), F.lit(r"\p{L}+"), F.lit(0))).alias("word"))
    counts = talk.groupBy("word").agg(F.count("*").alias("accesses")).join(vocab.select("word", "id"), "word", "left")
    counts = counts.select(F.lit("word").alias("feature"), F.coalesce("id", F.lit(-1)).alias("id"), "accesses")
    return mapping.relevance(loaded, counts)


_TALK = VOCAB_SQL + r""", talk AS (SELECT unnest(regexp_extract_all(lower(text), '\p{L}+')) AS word FROM conversations)"""


@query(
    "join_anti_unseen_ids",
    f"WITH {_TALK} SELECT word, count(*) AS uses FROM talk WHERE word NOT IN (SELECT word FROM vocab) GROUP BY word",
)
def join_anti_unseen_ids(spark, sf_dir):
    talk = table(spark, sf_dir, "conversations").select(F.explode(F.regexp_extract_all(F.lower("text"), F.lit(r"\p{L}+"), F.lit(0))).alias("word"))
    vocab = word_uses(spark, sf_dir).select("word").distinct()
    return talk.groupBy("word").agg(F.count("*").alias("uses")).join(vocab, "word", "left_anti")


@query(
    "join_semi_seen_ids",
    f"WITH {_TALK} SELECT word, count(*) AS uses FROM talk WHERE word IN (SELECT word FROM vocab) GROUP BY word",
)
def join_semi_seen_ids(spark, sf_dir):
    talk = table(spark, sf_dir, "conversations").select(F.explode(F.regexp_extract_all(F.lower("text"), F.lit(r"\p{L}+"), F.lit(0))).alias("word"))
    vocab = word_uses(spark, sf_dir).select("word").distinct()
    return talk.groupBy("word").agg(F.count("*").alias("uses")).join(vocab, "word", "left_semi")


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Learned folding of the words to 10 % of the rows beside modulo and random hashing: collisions and purity."""
    c, p = _setup(spark, sf_dir, **_mode("weight_and_filter"))
    counts = settle(c.select("feature", "id", "accesses", "value"))
    rows = p.row_budget
    uses = counts.select("feature", "id", F.explode(F.array(
        F.struct(F.lit("fr").alias("class"), F.round(F.col("accesses") * F.col("value") / 1e6).cast("long").alias("n")),
        F.struct(F.lit("other").alias("class"), (F.col("accesses") - F.round(F.col("accesses") * F.col("value") / 1e6)).cast("long").alias("n")),
    )).alias("u")).select("feature", "id", "u.*")
    maps = {"learned": mapping.emit(c, chain.fold_local(c, p)), "modulo": baselines.modulo(counts, rows), "random_hash": baselines.hashed(counts, rows)}
    out = None
    for name, m in maps.items():
        m = settle(m)
        one = metrics.collisions(m, counts).join(metrics.purity(m, uses), ["feature", "slot"]).select(F.lit(name).alias("method"), "ids", "rows_used", "id_pairs", "use_pairs", "purity")
        out = one if out is None else out.unionByName(one)
    return out


query("flagship_word_folding")(flagship)
