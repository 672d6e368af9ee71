"""URL filter rules by a sort-merge range join, with built-in functions only.

The labels of a host, reversed and each followed by a dot, make a canonical key: ``a.example.net``
becomes ``net.example.a.``. A rule's host and all its subdomains are then one interval of keys,
and the intervals of different rules are nested or disjoint. Rules become segment borders that
carry the stack of rules active from there on; borders and urls are sorted together by one range
exchange and a sweep hands every url the stack of the last border before it. Only that stack is
searched for path prefixes.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from idfold.llm.common import settle, table

#: The production rules (host, path, verdict).
RULES = (
    ("net", "/", "block"),
    ("example.net", "/en/", "allow"),
    ("example.com", "/de/", "block"),
    ("org", "/fr/", "allow"),
)

RULE_SCHEMA = "rule_host string, rule_path string, rule_verdict string"


def split_url(url: Column) -> tuple[Column, Column]:
    """Host (A-Z lower-cased) and path of a url; both empty without ``://``."""
    known = F.coalesce(F.contains(url, F.lit("://")), F.lit(False))
    rest = F.substring(url, F.locate("://", url) + 3, F.length(url))
    host = F.regexp_extract(rest, r"^[^/?#]*", 0)
    path = F.regexp_extract(F.substring(rest, F.length(host) + 1, F.length(rest)), r"^[^?#]*", 0)
    lower = F.translate(host, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    return F.when(known, lower).otherwise(F.lit("")), F.when(known, path).otherwise(F.lit(""))


def host_key(host: Column) -> Column:
    """Reversed labels, each followed by a dot; the empty host has the empty key."""
    return F.when(host == "", F.lit("")).otherwise(F.concat(F.concat_ws(".", F.reverse(F.split(host, r"\."))), F.lit(".")))


def rule_borders(rules: DataFrame) -> DataFrame:
    """(key, stack): the rules active from ``key`` on, for both ends of every rule host's interval.

    A host's stack holds its own rules and those of its ancestors, found by an equi-join on label
    prefixes of the key. A dot sorts just before a slash, so the key with its last dot turned into a
    slash is the first key after the interval.
    """
    own = (
        rules.where((F.col("rule_host") != "") & F.col("rule_path").isNotNull() & F.col("rule_verdict").isNotNull())
        .dropDuplicates(["rule_host", "rule_path", "rule_verdict"])
        .select(
            host_key(F.col("rule_host")).alias("key"),
            F.struct(
                (F.length("rule_host") + F.length("rule_path")).alias("n"),
                F.length("rule_host").alias("n_host"),
                F.concat("rule_host", "rule_path").alias("rule"),
                F.col("rule_path").alias("path"),
                F.col("rule_verdict").alias("verdict"),
            ).alias("item"),
        )
    )
    hosts = own.groupBy("key").agg(F.collect_list("item").alias("items"))
    labels = F.split(F.expr("substring(key, 1, length(key) - 1)"), r"\.")
    ancestors = hosts.select(
        "key",
        F.explode(
            F.transform(F.sequence(F.lit(1), F.size(labels)), lambda n: F.concat(F.concat_ws(".", F.slice(labels, F.lit(1), n)), F.lit(".")))
        ).alias("above"),
    )
    stacks = (
        ancestors.join(hosts.select(F.col("key").alias("above"), "items"), "above")
        .groupBy("key")
        .agg(
            F.flatten(F.collect_list("items")).alias("opened"),
            F.flatten(F.collect_list(F.when(F.col("above") != F.col("key"), F.col("items")))).alias("closed"),
        )
    )
    after = F.concat(F.expr("substring(key, 1, length(key) - 1)"), F.lit("/"))
    return stacks.select(
        F.explode(
            F.array(
                F.struct(F.col("key").alias("key"), F.col("opened").alias("stack")),
                F.struct(after.alias("key"), F.col("closed").alias("stack")),
            )
        ).alias("e")
    ).select("e.*")


def judge(
    pages: DataFrame, rules: DataFrame, *, id_col: str = "page_id", url_col: str = "url", default: str = "allow", partitions: int | None = None
) -> DataFrame:
    """page_id, host, path, rule, verdict for every row of ``pages``.

    A rule fits its host and all subdomains if the path starts with the rule's path. The longest
    rule text wins, then the longer host, then the greater text, then ``allow`` over other verdicts. Rows that no rule fits get a null rule and ``default``. Null urls and
    urls without ``://`` have empty host and path. Rules with an empty or null part are ignored;
    repeated rules count once; repeated pages keep their own rows; extra columns are ignored.
    """
    spark = pages.sparkSession
    partitions = partitions or int(spark.conf.get("spark.sql.shuffle.partitions"))
    host, path = split_url(F.col(url_col))
    points = pages.select(F.col(id_col).alias("page_id"), host.alias("host"), path.alias("path")).select(
        host_key(F.col("host")).alias("key"), F.lit(1).alias("kind"), "page_id", "host", "path"
    )
    borders = rule_borders(rules).select("key", F.lit(0).alias("kind"), "stack")
    # Urls of one hot host are told apart by path and id, so that the ranges stay even.
    ranged = settle(
        points.unionByName(borders, allowMissingColumns=True)
        .repartitionByRange(partitions, "key", "kind", F.xxhash64("path", "page_id"))
        .withColumn("part", F.spark_partition_id())
    )
    # The border in force where a range begins: one row per range at most.
    last = ranged.where("kind = 0").groupBy("part").agg(F.max_by("stack", "key").alias("stack"))
    ranges = ranged.groupBy("part").agg(F.count("*").alias("n")).select("part")
    inherited = ranges.join(last, "part", "left").select(
        "part", F.last("stack", ignorenulls=True).over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)).alias("inherited")
    )
    sweep = Window.partitionBy("part").orderBy("key", "kind").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    active = F.coalesce(F.col("stack_now"), F.col("inherited"))
    fits = F.filter(active, lambda r: F.startswith(F.col("path"), r["path"]))
    best = F.array_max(
        F.transform(
            fits,
            lambda r: F.struct(r["n"].alias("n"), r["n_host"].alias("n_host"), r["rule"].alias("rule"), (r["verdict"] == "allow").alias("ok"), r["verdict"].alias("verdict")),
        )
    )
    return (
        ranged.withColumn("stack_now", F.last("stack", ignorenulls=True).over(sweep))
        .where("kind = 1")
        .join(F.broadcast(inherited), "part")
        .select("page_id", "host", "path", best.alias("best"))
        .select("page_id", "host", "path", F.col("best.rule").alias("rule"), F.coalesce(F.col("best.verdict"), F.lit(default)).alias("verdict"))
    )


def rule_table(spark: SparkSession, rules=RULES) -> DataFrame:
    """The given rules as rows, without Python on the executors."""
    rows = [F.struct(*[F.lit(x).alias(n) for x, n in zip(r, ("rule_host", "rule_path", "rule_verdict"), strict=True)]) for r in rules]
    return spark.range(1).select(F.explode(F.array(*rows)).alias("r")).select("r.*")


def op10_url_range_join(spark, sf_dir: str) -> DataFrame:
    return judge(table(spark, sf_dir, "pages"), rule_table(spark))


SQL = r"""
WITH rules(rule, rhost, rpath, v) AS (VALUES ('net/', 'net', '/', 'block'), ('example.net/en/', 'example.net', '/en/', 'allow'),
                                             ('example.com/de/', 'example.com', '/de/', 'block'), ('org/fr/', 'org', '/fr/', 'allow')),
cut AS (SELECT page_id, CASE WHEN contains(url, '://') THEN substr(url, instr(url, '://') + 3) ELSE '' END AS rest FROM pages),
parts AS (SELECT page_id, translate(regexp_extract(rest, '^[^/?#]*'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
                 regexp_extract(substr(rest, length(regexp_extract(rest, '^[^/?#]*')) + 1), '^[^?#]*') AS path FROM cut),
hits AS (SELECT page_id, host, path, rule, v,
                row_number() OVER (PARTITION BY page_id ORDER BY length(rule) DESC NULLS LAST) AS nth
         FROM parts LEFT JOIN rules ON (host = rhost OR ends_with(host, '.' || rhost)) AND starts_with(path, rpath))
SELECT page_id, host, path, rule, coalesce(v, 'allow') AS verdict FROM hits WHERE nth = 1
"""
