"""Graphs on the given tables. Every builder reads only the columns it names."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from starfold.sources.graphs import normalize_edges


def table(spark: SparkSession, sf_dir: str, name: str, columns: list[str] | None = None, where: str | None = None) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    if where:
        df = df.where(where)
    return df.select(*columns) if columns else df


def _pairs(df: DataFrame, a, b) -> DataFrame:
    return normalize_edges(df.select(a.cast("long").alias("a"), b.cast("long").alias("b")))


def order_part(spark, d):
    return _pairs(table(spark, d, "lineitem", ["l_orderkey", "l_partkey"]), 2 * F.col("l_orderkey"), 2 * F.col("l_partkey") + 1)


def customer_supplier(spark, d):
    o = table(spark, d, "orders", ["o_orderkey", "o_custkey"])
    li = table(spark, d, "lineitem", ["l_orderkey", "l_suppkey"])
    return _pairs(o.join(li, o.o_orderkey == li.l_orderkey), 2 * F.col("o_custkey"), 2 * F.col("l_suppkey") + 1)


def customer_order(spark, d):
    return _pairs(table(spark, d, "orders", ["o_orderkey", "o_custkey"]), 2 * F.col("o_custkey"), 2 * F.col("o_orderkey") + 1)


def nation_region(spark, d):
    return _pairs(table(spark, d, "nation", ["n_nationkey", "n_regionkey"]), 2 * F.col("n_regionkey"), 2 * F.col("n_nationkey") + 1)


def _chain(df: DataFrame, key, order: list, vertex: str) -> DataFrame:
    w = Window.partitionBy(key).orderBy(*order)
    return _pairs(df.withColumn("nxt", F.lead(vertex).over(w)), F.col(vertex), F.col("nxt"))


def event_chain(spark, d):
    """Next event in id order: ids are cut into blocks, so the window never spans all rows; block ends are joined by the least later id."""
    ev = table(spark, d, "events", ["event_id"]).withColumn("blk", F.floor(F.col("event_id") / 65536))
    w = Window.partitionBy("blk").orderBy("event_id")
    inner = ev.withColumn("nxt", F.lead("event_id").over(w))
    ends = ev.groupBy("blk").agg(F.max("event_id").alias("event_id"), F.min("event_id").alias("first"))
    nxt = Window.orderBy("blk")
    bridge = ends.withColumn("nxt", F.lead("first").over(nxt)).select("event_id", "nxt")
    return _pairs(inner.select("event_id", "nxt").unionByName(bridge), F.col("event_id"), F.col("nxt"))


def user_event_chain(spark, d):
    return _chain(table(spark, d, "events", ["event_id", "user_id", "ts"]), "user_id", ["ts", "event_id"], "event_id")


def session_links(spark, d):
    """(key, a, b): consecutive events of a user, the key, less than half an hour apart."""
    ev = table(spark, d, "events", ["event_id", "user_id", "ts"])
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    near = ev.withColumn("nxt", F.lead("event_id").over(w)).withColumn("at", F.lead("ts").over(w))
    near = near.where(F.unix_micros(F.col("at").cast("timestamp")) - F.unix_micros(F.col("ts").cast("timestamp")) < 1_800_000_000)
    return near.select(F.col("user_id").alias("key"), F.col("event_id").alias("a"), F.col("nxt").alias("b"))


def session_chain(spark, d):
    links = session_links(spark, d)
    return _pairs(links, F.col("a"), F.col("b"))


def turn_chain(spark, d):
    t = table(spark, d, "conversations", ["conv_id", "turn"]).withColumn("v", F.col("conv_id") * 1000 + F.col("turn"))
    return _chain(t, "conv_id", ["turn"], "v")


def line_item_chain(spark, d):
    t = table(spark, d, "lineitem", ["l_orderkey", "l_linenumber"]).distinct().withColumn("v", F.col("l_orderkey") * 10 + F.col("l_linenumber"))
    return _chain(t, "l_orderkey", ["l_linenumber"], "v")


def rare_return_orders(spark, d):
    li = table(spark, d, "lineitem", ["l_orderkey", "l_partkey"], "l_returnflag = 'R' and l_quantity >= 49")
    return _pairs(li, 2 * F.col("l_orderkey"), 2 * F.col("l_partkey") + 1)


def rare_return_parts(spark, d):
    li = table(spark, d, "lineitem", ["l_partkey", "l_suppkey"], "l_returnflag = 'R' and l_quantity >= 50")
    return _pairs(li, 2 * F.col("l_partkey"), 2 * F.col("l_suppkey") + 1)


def page_host(spark, d):
    p = table(spark, d, "pages", ["page_id", "url"]).select("page_id", F.parse_url("url", F.lit("HOST")).alias("h"))
    return _named_bipartite(p, "page_id", "h")


def page_link(spark, d):
    p = table(spark, d, "pages", ["page_id", "html"]).select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("h"))
    return _named_bipartite(p, "page_id", "h")


def doc_line_bipartite(spark, d, least: int = 40):
    doc = table(spark, d, "documents", ["doc_id", "text"])
    lines = doc.select("doc_id", F.explode(F.split("text", "\n")).alias("x")).select("doc_id", F.trim("x").alias("h")).where(F.length("h") >= least)
    return _named_bipartite(lines, "doc_id", "h")


def _named_bipartite(df: DataFrame, left: str, key: str) -> DataFrame:
    """2·left and 2·(dense rank of key)+1: ranks come from counts of key ranges, never from one window over all rows."""
    pairs = df.select(F.col(left).alias("l"), F.col(key).alias("k")).where("l is not null and k is not null").distinct()
    from starfold.sources.graphs import encode_vertices

    _, names = encode_vertices(pairs.select(F.col("k").alias("p"), F.col("k").alias("q")), "p", "q")
    return _pairs(pairs.join(names.withColumnRenamed("key", "k"), "k"), 2 * F.col("l"), 2 * (F.col("vertex") + 1) + 1)


def doc_exact(spark, d):
    """Each document linked with the least document of the same text: a star for every group, never a clique."""
    doc = table(spark, d, "documents", ["doc_id", "text"]).select("doc_id", F.sha2("text", 256).alias("k"))
    return _pairs(doc.join(doc.groupBy("k").agg(F.min("doc_id").alias("first")), "k"), F.col("first"), F.col("doc_id"))


def doc_shared_line(spark, d, least: int = 40):
    """Documents that share a trimmed line, as stars round the least document of the line (same components as all pairs)."""
    doc = table(spark, d, "documents", ["doc_id", "text"])
    lines = doc.select("doc_id", F.explode(F.split("text", "\n")).alias("x")).select("doc_id", F.trim("x").alias("h")).where(F.length("h") >= least)
    keyed = lines.select("doc_id", F.sha2("h", 256).alias("k")).distinct()
    return _pairs(keyed.join(keyed.groupBy("k").agg(F.min("doc_id").alias("first")), "k"), F.col("first"), F.col("doc_id"))


def doc_benchmark(spark, d, least: int = 20):
    line = lambda t, i: table(spark, d, t, [i, "text"]).select(F.col(i).alias("i"), F.explode(F.split("text", "\n")).alias("x")).select("i", F.trim("x").alias("h")).where(F.length("h") >= least).distinct()
    a, b = line("documents", "doc_id"), line("benchmark", "item_id").withColumnRenamed("i", "j")
    return _pairs(a.join(b, "h"), 2 * F.col("i"), 2 * F.col("j") + 1)


def event_prop_graph(spark, d):
    ev = table(spark, d, "events", ["user_id", "props"]).select("user_id", F.get_json_object("props", "$.k").cast("long").alias("k"))
    return _pairs(ev, 2 * F.col("user_id"), 2 * F.col("k") + 1)


def vector_neighbours(spark, d, least: float = 0.3, block: int = 256):
    """Pairs of cosine at least ``least``: blocks of vectors are compared block with block, each block a task of fixed size."""
    v = table(spark, d, "embeddings", ["vec_id", "embedding"])
    v = v.withColumn("blk", F.floor(F.col("vec_id") / block))
    packs = v.groupBy("blk").agg(F.sort_array(F.collect_list(F.struct("vec_id", "embedding"))).alias("rows"))
    left, right = packs.select(F.col("blk").alias("x"), F.col("rows").alias("p")), packs.select(F.col("blk").alias("y"), F.col("rows").alias("q"))

    def compare(batches):
        import numpy as np
        import pandas as pd

        for pdf in batches:
            for p, q in zip(pdf["p"], pdf["q"]):
                i, j = np.array([r["vec_id"] for r in p]), np.array([r["vec_id"] for r in q])
                a, b = np.array([r["embedding"] for r in p], float), np.array([r["embedding"] for r in q], float)
                s = (a / np.linalg.norm(a, axis=1, keepdims=True)) @ (b / np.linalg.norm(b, axis=1, keepdims=True)).T
                m, n = np.nonzero((s >= least) & (i[:, None] < j[None, :]))
                yield pd.DataFrame({"a": i[m], "b": j[n]})

    return normalize_edges(left.join(right, F.col("x") <= F.col("y")).select("p", "q").mapInPandas(compare, "a long, b long"))


def schema_graph(spark, d):
    """Every foreign key of the star schema; kinds are told apart by the id modulo six."""
    o = table(spark, d, "orders", ["o_orderkey", "o_custkey"])
    li = table(spark, d, "lineitem", ["l_orderkey", "l_partkey", "l_suppkey"])
    kind = lambda c, k: (6 * F.col(c) + k).cast("long")
    two = lambda df, a, b: df.select(a.alias("a"), b.alias("b"))
    parts = [
        two(table(spark, d, "nation", ["n_nationkey", "n_regionkey"]), kind("n_regionkey", 0), kind("n_nationkey", 1)),
        two(table(spark, d, "customer", ["c_custkey", "c_nationkey"]), kind("c_nationkey", 1), kind("c_custkey", 2)),
        two(table(spark, d, "supplier", ["s_suppkey", "s_nationkey"]), kind("s_nationkey", 1), kind("s_suppkey", 3)),
        two(o, kind("o_custkey", 2), kind("o_orderkey", 4)),
        two(li, kind("l_orderkey", 4), kind("l_partkey", 5)),
        two(li, kind("l_suppkey", 3), kind("l_partkey", 5)),
    ]
    whole = parts[0]
    for p in parts[1:]:
        whole = whole.unionByName(p)
    return normalize_edges(whole)


def region_tree(spark, d):
    """Regions, their nations and the customers of these, as a forest of depth two. Ids of an upper level are less, so that a walk down meets only larger ones."""
    two = lambda t, columns, a, b: table(spark, d, t, columns).select(a.cast("long").alias("a"), b.cast("long").alias("b"))
    nations = two("nation", ["n_nationkey", "n_regionkey"], F.col("n_regionkey") - 2_000_000, F.col("n_nationkey") - 1_000_000)
    return normalize_edges(nations.unionByName(two("customer", ["c_custkey", "c_nationkey"], F.col("c_nationkey") - 1_000_000, F.col("c_custkey"))))


def four_paths(spark, d):
    """Customers in fours of neighbouring keys, each a path; the 24 orders of its ids take turns."""
    from itertools import permutations

    keys = table(spark, d, "customer", ["c_custkey"]).where("c_custkey is not null").distinct().withColumn("g", F.shiftright("c_custkey", 2))
    w = Window.partitionBy("g").orderBy("c_custkey")
    orders = F.array(*[F.array(*map(F.lit, p)) for p in permutations(range(4))])
    placed = keys.withColumn("j", F.row_number().over(w) - 1).select(
        "g", "j", (4 * F.col("g") + F.get(F.get(orders, F.pmod("g", F.lit(24)).cast("int")), F.col("j"))).alias("v"),
    )
    return _pairs(placed.withColumn("nxt", F.lead("v").over(Window.partitionBy("g").orderBy("j"))), F.col("v"), F.col("nxt"))


BUILDERS = {f.__name__: f for f in (
    order_part, customer_supplier, customer_order, nation_region, event_chain, user_event_chain, session_chain, turn_chain,
    line_item_chain, rare_return_orders, rare_return_parts, page_host, page_link, doc_line_bipartite, doc_exact,
    doc_shared_line, doc_benchmark, event_prop_graph, vector_neighbours, schema_graph,
)}
