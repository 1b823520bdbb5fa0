"""Sharding: a hierarchical weighted hash tree of regions, racks and shards.

A row descends from the root. At each level every child draws an exponential arrival, the negative logarithm of
a hash of (row key, child) over the child's weight, and the earliest wins. A child's draw depends on its own
name and weight alone, so a changed weight moves rows only into or out of the subtree whose weight changed.
A shard that is added opens a new region, whose draw competes at the root: rows move into it and nowhere else.

Defined results: a null text has size 8 and checksum 0; a null id is the key "null"; repeated rows share a
shard and have slots of their own.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from starfold.llm.shared import stored


def layout(shards: int, racks: int = 2, per_rack: int = 4) -> list[tuple[str, str, int, float]]:
    """(region, rack, shard, weight) of the first ``shards`` shards. Regions hold ``racks`` racks of ``per_rack`` shards."""
    return [(f"g{s // (racks * per_rack)}", f"g{s // (racks * per_rack)}/k{s % (racks * per_rack) // per_rack}", s, 1.0) for s in range(shards)]


def grown(tree: list[tuple[str, str, int, float]], weight: float = 1.0) -> list[tuple[str, str, int, float]]:
    """The tree with one more shard in a region of its own."""
    s = max(x[2] for x in tree) + 1
    return [*tree, (f"n{s}", f"n{s}/k0", s, weight)]


def _draw(key: Column, name: str, weight: float) -> Column:
    part = F.conv(F.substring(F.md5(F.concat(key, F.lit(f"|{name}")).cast("binary")), 1, 13), 16, 10).cast("double")
    return -F.log((part + 0.5) / float(1 << 52)) / F.lit(weight)


def _weights(tree, level: int) -> list[tuple[str, float]]:
    found: dict = {}
    for row in tree:
        if row[3] > 0:
            found[row[level]] = found.get(row[level], 0.0) + row[3]
    return list(found.items())


def with_shard(df: DataFrame, key: Column, tree: list[tuple[str, str, int, float]], out: str = "shard") -> DataFrame:
    """Adds the shard of each row, one column a level so that no draw is computed twice in a branch."""
    if not tree or sum(r[3] for r in tree) <= 0:
        raise ValueError("the tree needs a shard of positive weight")
    region = _pick(df.withColumn("_key", key), _weights(tree, 0), "_region")
    for level, here, name in ((1, "_region", "_rack"), (2, "_rack", "_leaf")):
        options = {}
        for r in tree:
            options.setdefault(r[level - 1], []).append(r)
        value = F.lit(None).cast("string")
        for parent, rows in options.items():
            value = F.when(F.col(here) == parent, _best([(str(n), w) for n, w in _weights(rows, level)], F.col("_key"))).otherwise(value)
        region = region.withColumn(name, value)
    return region.withColumn(out, F.col("_leaf").cast("int")).drop("_key", "_region", "_rack", "_leaf")


def _best(children: list[tuple[str, float]], key: Column) -> Column:
    if len(children) == 1:
        return F.lit(children[0][0])
    return F.least(*[F.struct(_draw(key, n, w).alias("d"), F.lit(n).alias("n")) for n, w in children])["n"]


def _pick(df: DataFrame, children: list[tuple[str, float]], out: str) -> DataFrame:
    return df.withColumn(out, _best([(str(n), w) for n, w in children], F.col("_key")))


def with_slots(df: DataFrame, shard: str, order: list[str], digits: int) -> DataFrame:
    """Gapless places from 0 within each shard, in the order of the md5 of the first order column.

    Rows are numbered within (shard, md5 prefix of ``digits``); the counts of the prefixes before are added. The
    prefix grows with the table, so no task numbers a whole shard, and the place does not depend on it.
    """
    mark = F.md5(F.coalesce(F.col(order[0]).cast("string"), F.lit("null")).cast("binary"))
    rows = stored(df.withColumn("_mark", mark).withColumn("_cell", F.substring("_mark", 1, digits)))
    sizes = rows.groupBy(shard, "_cell").agg(F.count("*").alias("_n"))
    before = Window.partitionBy(shard).orderBy("_cell").rowsBetween(Window.unboundedPreceding, -1)
    offsets = sizes.select(shard, "_cell", F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_base"))
    place = F.row_number().over(Window.partitionBy(shard, "_cell").orderBy("_mark", *order))
    return rows.withColumn("_k", place).join(offsets, [shard, "_cell"]).withColumn("slot", (F.col("_base") + F.col("_k") - 1).cast("long")).drop("_mark", "_cell", "_k", "_base")


def shard_documents(docs: DataFrame, *, shards: int = 24, id_col: str = "doc_id", text: str = "text", rows_per_cell: int = 4096) -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot and grown_shard (the shard with one shard more) for every row."""
    raw = F.coalesce(F.col(text), F.lit(""))
    key = F.coalesce(F.col(id_col).cast("string"), F.lit("null"))
    base = docs.select(
        F.col(id_col).alias("doc_id"), (F.octet_length(raw) + 8).cast("long").alias("size"),
        F.crc32(raw.cast("binary")).alias("text_crc32"), key.alias("_id"),
    )
    tree = layout(shards)
    placed = with_shard(with_shard(base, F.col("_id"), tree), F.col("_id"), grown(tree), "grown_shard")
    digits = 0
    total = docs.count()
    while shards * 16**digits * rows_per_cell < total:
        digits += 1
    return with_slots(placed.drop("_id"), "shard", ["doc_id", "size", "text_crc32"], digits).select(
        "doc_id", "size", "text_crc32", F.lit("key").alias("law"), "shard", "slot", "grown_shard"
    )
