"""Edge relations: normalization, twins and generated families."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def normalize_edges(df: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """Simple undirected edges: nulls and loops dropped, smaller id first, distinct."""
    x, y = F.col(a), F.col(b)
    return (
        df.where(x.isNotNull() & y.isNotNull() & (x != y))
        .select(F.least(x, y).alias("a"), F.greatest(x, y).alias("b"))
        .distinct()
    )


def twins(edges: DataFrame) -> DataFrame:
    """Both directions of each edge from one scan."""
    return edges.select(
        F.explode(
            F.array(
                F.struct(F.col("a").alias("src"), F.col("b").alias("dst")),
                F.struct(F.col("b").alias("src"), F.col("a").alias("dst")),
            )
        ).alias("e")
    ).select("e.src", "e.dst")


def vertices_of(edges: DataFrame) -> DataFrame:
    return edges.select(F.explode(F.array("a", "b")).alias("vertex")).distinct()


def encode_vertices(edges: DataFrame, a: str, b: str, partitions: int = 32) -> tuple[DataFrame, DataFrame]:
    """Dense order-keeping long ids for keys of any orderable type, and the dictionary (key, vertex).

    Keys are range-partitioned; each range numbers its own keys and adds the count of the ranges before it.
    Nothing is hashed, so no two keys can meet, and no window spans all rows.
    """
    from pyspark.sql import Window

    keys = edges.select(F.explode(F.array(F.col(a), F.col(b))).alias("key")).where("key is not null").distinct()
    ranged = keys.repartitionByRange(partitions, "key").withColumn("part", F.spark_partition_id())
    from starfold.plans.loop import materialize

    ranged = materialize(ranged)
    sizes = ranged.groupBy("part").count()
    offsets = sizes.withColumn(
        "base", F.sum("count").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1))
    ).select("part", F.coalesce("base", F.lit(0)).alias("base"))
    numbered = ranged.withColumn("n", F.row_number().over(Window.partitionBy("part").orderBy("key")))
    dictionary = numbered.join(offsets, "part").select("key", (F.col("base") + F.col("n") - 1).alias("vertex"))
    coded = (
        edges.select(F.col(a).alias("ka"), F.col(b).alias("kb"))
        .join(dictionary.select(F.col("key").alias("ka"), F.col("vertex").alias("a")), "ka")
        .join(dictionary.select(F.col("key").alias("kb"), F.col("vertex").alias("b")), "kb")
        .select("a", "b")
    )
    return normalize_edges(coded), dictionary


def relabel(edges: DataFrame, how: str = "shuffle", seed: int = 0) -> tuple[DataFrame, DataFrame]:
    """Rename vertices so that a long sequential chain loses its order; returns edges and (vertex, new)."""
    if how == "degree":
        base = twins(edges).groupBy(F.col("src").alias("vertex")).agg(F.count("*").alias("degree"))
        first = -F.col("degree")
    else:
        base = vertices_of(edges)
        first = -F.col("vertex") if how == "reverse" else F.xxhash64("vertex", F.lit(seed))
    # Ranks come from counts of key ranges, never from one window over all vertices.
    key = base.select(F.struct(first.alias("k0"), F.col("vertex").alias("k1")).alias("p"))
    _, names = encode_vertices(key.withColumn("q", F.col("p")), "p", "q")
    names = names.select(F.col("key.k1").alias("vertex"), F.col("vertex").alias("new"))
    renamed = (
        edges.join(names.select(F.col("vertex").alias("a"), F.col("new").alias("na")), "a")
        .join(names.select(F.col("vertex").alias("b"), F.col("new").alias("nb")), "b")
        .select(F.col("na").alias("a"), F.col("nb").alias("b"))
    )
    return normalize_edges(renamed), names


def seq_path(spark: SparkSession, e: int) -> DataFrame:
    """i - i+1 over 2^e vertices."""
    return spark.range((1 << e) - 1).select(F.col("id").alias("a"), (F.col("id") + 1).alias("b"))


def shuffled_path(spark: SparkSession, e: int, seed: int = 7) -> DataFrame:
    """A path whose vertices are renamed by an odd multiplier and an offset modulo 2^e (a permutation)."""
    n = 1 << e
    mult, add = (2654435761 + 2 * seed) | 1, 12345 + seed
    code = lambda c: F.pmod((c % n) * (mult % n) + add, F.lit(n))
    return spark.range(n - 1).select(code(F.col("id")).alias("a"), code(F.col("id") + 1).alias("b"))


def bridged_grid(spark: SparkSession, r: int, c: int) -> DataFrame:
    """Rows by columns, row-major from 1, and vertex 0 joined to the first column of each row."""
    cell = spark.range(1, r * c + 1)
    col = (F.col("id") - 1) % c
    row = F.floor((F.col("id") - 1) / c)
    edge = lambda cond, x, y: F.when(cond, F.struct(x.cast("long").alias("a"), y.cast("long").alias("b")))
    return (
        cell.select(
            F.explode(
                F.array(
                    edge(col < c - 1, F.col("id"), F.col("id") + 1),
                    edge(row < r - 1, F.col("id"), F.col("id") + c),
                    edge(col == 0, F.lit(0), F.col("id")),
                )
            ).alias("e")
        )
        .where("e is not null")
        .select("e.a", "e.b")
    )


def binary_tree(spark: SparkSession, e: int) -> DataFrame:
    return spark.range(1, 1 << e).select(F.floor((F.col("id") - 1) / 2).cast("long").alias("a"), F.col("id").alias("b"))


def from_pairs(spark: SparkSession, pairs: list[tuple[int, int]]) -> DataFrame:
    return spark.createDataFrame(pairs or [], "a long, b long")


def figure_path(spark: SparkSession) -> DataFrame:
    return from_pairs(spark, [(1, 3), (3, 4), (2, 4)])


def all_four_paths(spark: SparkSession) -> DataFrame:
    """The 24 labellings of a path on four vertices, offset into one disjoint union."""
    from itertools import permutations

    pairs = []
    for i, p in enumerate(permutations(range(4))):
        pairs += [(10 * i + p[j], 10 * i + p[j + 1]) for j in range(3)]
    return from_pairs(spark, pairs)


def star_pair_twins(spark: SparkSession, a: int, b: int, small_to_large: bool = True) -> DataFrame:
    """Directed edges of two stars (roots 0 and a) with one one-way edge between the roots."""
    pairs = [(0, i) for i in range(1, a)] + [(a, i) for i in range(a + 1, a + b)]
    both = pairs + [(y, x) for x, y in pairs] + [(0, a) if small_to_large else (a, 0)]
    return spark.createDataFrame(both, "src long, dst long")


def disjoint_union(graphs: list[DataFrame], stride: int) -> DataFrame:
    moved = [g.select((F.col("a") + i * stride).alias("a"), (F.col("b") + i * stride).alias("b")) for i, g in enumerate(graphs)]
    return reduce(DataFrame.unionByName, moved)


def induced_subgraph(edges: DataFrame, vertices: DataFrame) -> DataFrame:
    v = vertices.select("vertex")
    return edges.join(v.withColumnRenamed("vertex", "a"), "a", "left_semi").join(
        v.withColumnRenamed("vertex", "b"), "b", "left_semi"
    ).select("a", "b")
