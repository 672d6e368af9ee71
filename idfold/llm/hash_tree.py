"""Sharding by a hierarchical weighted hash tree, with built-in functions only.

A row descends region, rack and shard. At every node each child gets a draw, an exponential variate
from the hash of (row key, path of the child) divided by the child's weight, and the least draw wins.
Draws of a child depend on nothing but the row and that child's path, so a change of weight moves
rows only into or out of the subtree whose weight changed, and nodes of one name on different levels
or under different parents draw independently.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from idfold.llm.common import table, unit_draw

#: Sub-buckets of a shard for numbering its rows without bringing a whole shard into one task.
SLOT_BUCKETS = 512


@dataclass(frozen=True)
class Leaf:
    region: str
    rack: str
    shard: int
    weight: float = 1.0


def default_tree(shards: int) -> tuple[Leaf, ...]:
    """Two regions of two racks of two shards; each shard beyond the eighth is a region of its own.

    A new region draws rows from all others, and inside it only the new shard can take them.
    """
    grid = [Leaf(f"r{s // 4}", f"r{s // 4}k{s // 2}", s) for s in range(min(shards, 8))]
    return tuple(grid + [Leaf(f"r{s}", f"r{s}k0", s) for s in range(8, shards)])


def _path(*names: object) -> str:
    """The path of a node as it enters the hash; names are escaped, so that no two paths are equal."""
    return "/".join(str(n).replace("%", "%25").replace("/", "%2F").replace(":", "%3A") for n in names)


def _least(key: Column, parent: tuple[str, ...], children: dict[str, float], then) -> Column:
    """Descend to the child with the least weighted draw; ties go to the first named."""
    names = sorted(children)
    if len(names) == 1:
        return then(names[0])
    draws = F.array(*[F.struct((-F.log(unit_draw(key, F.lit(_path(*parent, n)))) / F.lit(children[n])).alias("d"), F.lit(n).alias("n")) for n in names])
    winner = F.array_min(draws)["n"]
    out = None
    for name in names:
        out = F.when(winner == name, then(name)) if out is None else out.when(winner == name, then(name))
    return out


def descend(key: Column, leaves: tuple[Leaf, ...]) -> Column:
    """The shard that ``key`` falls to in the tree of ``leaves`` (leaves of weight 0 take nothing)."""
    live = [x for x in leaves if x.weight > 0]
    if not live:
        raise ValueError("a tree needs a leaf of positive weight")

    def total(level: str, **fixed: str) -> dict[str, float]:
        sums: dict[str, float] = {}
        for leaf in live:
            if all(getattr(leaf, k) == v for k, v in fixed.items()):
                name = str(getattr(leaf, level))
                sums[name] = sums.get(name, 0.0) + leaf.weight
        return sums

    def shard(region: str, rack: str) -> Column:
        return _least(key, (region, rack), total("shard", region=region, rack=rack), lambda s: F.lit(int(s)))

    def rack(region: str) -> Column:
        return _least(key, (region,), total("rack", region=region), lambda k: shard(region, k))

    return _least(key, (), total("region"), rack)


def shard_rows(
    docs: DataFrame,
    *,
    leaves: tuple[Leaf, ...] | None = None,
    grown: tuple[Leaf, ...] | None = None,
    id_col: str = "doc_id",
    text_col: str = "text",
    slot_buckets: int = SLOT_BUCKETS,
) -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard for every row.

    The law is ``key``: shard depends on the doc_id and the tree alone. Rows of a null doc_id share
    the key ``null``; null text has no bytes (size 1, CRC of nothing). Slots are gapless from 0 in
    each shard, ordered by (sub-bucket, doc_id, size, CRC); repeated rows get slots of their own.
    Extra columns are ignored.
    """
    leaves = leaves or default_tree(8)
    grown = grown or default_tree(len(leaves) + 1)
    key = F.coalesce(F.col(id_col).cast("string"), F.lit("null"))
    body = F.coalesce(F.col(text_col), F.lit("")).cast("binary")
    # By the whole row, so that many rows of one doc_id (or of none) fall into many buckets. Equal
    # rows, text and all, still share one; they can be told apart by nothing.
    bucket = F.floor(unit_draw(key, F.octet_length(body), F.crc32(body), F.lit("slot")) * slot_buckets).cast("int")
    placed = docs.select(F.col(id_col).alias("doc_id"), descend(key, leaves).alias("shard"), bucket.alias("bucket"))
    # Where each sub-bucket begins: shards x slot_buckets rows at most.
    begins = (
        placed.groupBy("shard", "bucket")
        .agg(F.count("*").alias("n"))
        .select("shard", "bucket", (F.sum("n").over(Window.partitionBy("shard").orderBy("bucket")) - F.col("n")).alias("begin"))
    )
    rows = docs.select(
        F.col(id_col).alias("doc_id"),
        (F.octet_length(body) + 1).cast("long").alias("size"),
        F.crc32(body).alias("text_crc32"),
        descend(key, leaves).alias("shard"),
        descend(key, grown).alias("grown_shard"),
        bucket.alias("bucket"),
    )
    place = Window.partitionBy("shard", "bucket").orderBy(F.asc_nulls_last("doc_id"), "size", "text_crc32")
    return (
        rows.withColumn("place", F.row_number().over(place) - 1)
        .join(F.broadcast(begins), ["shard", "bucket"])
        .select(
            "doc_id",
            "size",
            "text_crc32",
            F.lit("key").alias("law"),
            "shard",
            (F.col("begin") + F.col("place")).cast("long").alias("slot"),
            "grown_shard",
        )
    )


def op6_hash_tree_sharding(spark, sf_dir: str) -> DataFrame:
    return shard_rows(table(spark, sf_dir, "documents"))


def _draw_sql(name: str) -> str:
    return f"((('0x' || substr(md5(k || ':{name}'), 1, 12))::BIGINT + 0.5) / {float(1 << 48)})"


def _descend_sql(leaves: tuple[Leaf, ...]) -> str:
    """The descent as nested CASE expressions over the text key ``k``."""

    def least(level: str, parent: tuple[str, ...], pool: list[Leaf], then) -> str:
        sums: dict[str, float] = {}
        for leaf in pool:
            sums[str(getattr(leaf, level))] = sums.get(str(getattr(leaf, level)), 0.0) + leaf.weight
        names = sorted(sums)
        inside = {n: then([x for x in pool if str(getattr(x, level)) == n]) for n in names}
        if len(names) == 1:
            return inside[names[0]]
        draws = {n: f"(-ln({_draw_sql(_path(*parent, n))}) / {sums[n]})" for n in names}
        whens = " ".join(f"WHEN {' AND '.join(f'{draws[n]} <= {draws[o]}' for o in names if o != n)} THEN {inside[n]}" for n in names)
        return f"(CASE {whens} END)"

    shard = lambda pool: least("shard", (pool[0].region, pool[0].rack), pool, lambda last: str(last[0].shard))
    rack = lambda pool: least("rack", (pool[0].region,), pool, shard)
    return least("region", (), [x for x in leaves if x.weight > 0], rack)


def oracle(docs: str = "documents") -> str:
    """The same shards, slots and checksums as DuckDB SQL.

    The CRC-32 is folded over the hexadecimal digits of the text, four bits at a step, with the
    table of the reflected polynomial 0xEDB88320 built by rule.
    """
    step = "CASE WHEN c & 1 = 1 THEN xor(c >> 1, 3988292384) ELSE c >> 1 END"
    folds = "n"
    for _ in range(4):
        folds = step.replace("c", f"({folds})")
    table = f"list_transform(range(16), lambda n: {folds})"
    # Hexadecimal puts the high digit of a byte first; the CRC takes the low one first.
    digits = "list_transform(range(strlen(body) * 2), lambda i: instr('0123456789ABCDEF', substr(h, (i + CASE WHEN i % 2 = 0 THEN 2 ELSE 0 END)::BIGINT, 1)) - 1)"
    crc = f"xor(list_reduce(list_prepend(4294967295::BIGINT, d), lambda a, x: xor(a >> 4, t[(xor(a, x) & 15) + 1])), 4294967295)"
    return f"""WITH keyed AS (SELECT doc_id, coalesce(doc_id::VARCHAR, 'null') AS k, coalesce(text, '') AS body, hex(encode(coalesce(text, ''))) AS h FROM {docs}),
placed AS (SELECT doc_id, k, strlen(body) + 1 AS size, {_descend_sql(default_tree(8))} AS shard, {_descend_sql(default_tree(9))} AS grown_shard, {digits} AS d, {table} AS t FROM keyed),
checked AS (SELECT doc_id, k, size, shard, grown_shard, ({crc})::BIGINT AS text_crc32 FROM placed),
summed AS (SELECT *, floor((('0x' || substr(md5(k || ':' || (size - 1) || ':' || text_crc32 || ':slot'), 1, 12))::BIGINT + 0.5) / {float(1 << 48)} * {SLOT_BUCKETS})::INT AS bucket FROM checked)
SELECT doc_id, size, text_crc32, 'key' AS law, shard,
  row_number() OVER (PARTITION BY shard ORDER BY bucket, doc_id NULLS LAST, size, text_crc32) - 1 AS slot, grown_shard FROM summed"""
