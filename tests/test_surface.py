"""Readers, sinks, streams and the helpers round the labels."""

import sys

import pytest
from pyspark.sql import functions as F

from starfold.functions import keyed
from starfold.functions import measures as M
from starfold.operators import alternating as A
from starfold.operators import baselines as B
from starfold.sources import graphs as G
from starfold.sources import readers
from starfold.streaming.components import ComponentStream, keyed_components, session_components

SMALL = [(0, 1), (1, 2), (5, 6), (8, 9), (9, 10), (2, 7)]


def found(df):
    return {r.vertex: r.component for r in df.collect()}


def test_edge_lists_of_every_format(spark, tmp_path):
    want = sorted(SMALL)
    (tmp_path / "e.txt").write_text("# c\n% d\nc e\np edge 4 5\n" + "".join(f"{b}\t{a}\n" if a % 2 else f"a {a} {b} 3\n" for a, b in SMALL) + "1 1\n\nx y\n")
    assert sorted(map(tuple, readers.edge_list(spark, str(tmp_path / "e.txt")).collect())) == want
    for fmt in ("csv", "json", "orc", "parquet"):
        G.from_pairs(spark, SMALL).write.format(fmt).save(str(tmp_path / fmt))
        assert sorted(map(tuple, readers.edge_list(spark, str(tmp_path / fmt), fmt).collect())) == want


def test_generator_source_and_sinks(spark, tmp_path):
    spark.dataSource.register(readers.SyntheticGraphSource)
    tree = spark.read.format("synthetic_graph").option("family", "tree").option("size", "16").option("partitions", "3").load()
    r = A.connected_components(tree)
    assert set(found(r.labels).values()) == {0}
    readers.save_metrics(r, str(tmp_path / "m"), spark)
    assert spark.read.parquet(str(tmp_path / "m")).count() == r.n_steps
    readers.register(r, "tree", spark)
    assert spark.sql("SELECT count(*) AS n FROM tree_labels").first().n == 16


def test_stream_equals_batch(spark, tmp_path):
    for k in range(3):
        part = SMALL[2 * k:2 * k + 2] + SMALL[:1]
        G.from_pairs(spark, part).coalesce(1).write.parquet(str(tmp_path / "in" / f"k{k}"))
    stream = ComponentStream(spark, str(tmp_path / "snap"))
    rows = spark.readStream.schema("a long, b long").option("maxFilesPerTrigger", 1).option("recursiveFileLookup", "true").parquet(str(tmp_path / "in"))
    stream.start(rows, str(tmp_path / "check")).awaitTermination()
    assert found(stream.labels()) == B.union_find(G.from_pairs(spark, SMALL))
    stream.apply(G.from_pairs(spark, [(0, 99)]), 0)
    assert 99 not in found(stream.labels())


def test_sessions_of_a_stream_equal_those_of_the_table(spark, tmp_path):
    ev = spark.range(40).selectExpr("id as event_id", "id % 3 as user_id", "timestamp_seconds(id * 600 + (id div 20) * 7200) as ts")
    ev.coalesce(1).write.parquet(str(tmp_path / "ev"))
    late = spark.createDataFrame([(999, 7, 10_000_000)], "event_id long, user_id long, s long").selectExpr("event_id", "user_id", "timestamp_seconds(s) as ts")
    late.coalesce(1).write.parquet(str(tmp_path / "ev2"))
    rows = spark.readStream.schema(ev.schema).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", "true").parquet(str(tmp_path / "ev*"))
    q = session_components(rows).writeStream.format("memory").queryName("sessions").outputMode("append").option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start()
    q.awaitTermination()
    got = {tuple(r) for r in spark.table("sessions").collect()}
    assert got == {tuple(r) for r in session_components(ev).collect()}


KEYED = [(1, 0, 1), (1, 1, 2), (2, 1, 2), (1, 5, 6), (1, 6, 2), (2, 9, 9), (3, None, 4), (2, 8, 2), (1, 0, 1)]


def by_key(rows):
    parts = {k: [(a, b) for j, a, b in rows if j == k and a is not None] for k, _, _ in rows}
    want = {}
    for k, edges in parts.items():
        forest = keyed.Forest()
        for a, b in edges:
            forest.link(a, b)
        want |= {(k, v): c for v, c in forest.labels().items()}
    return want


def test_table_function_finds_components_within_a_key(spark):
    edges = spark.createDataFrame(KEYED, "key long, a long, b long")
    want = {(1, v): 0 for v in (0, 1, 2)} | {(1, 5): 0, (1, 6): 0, (2, 1): 1, (2, 2): 1, (2, 8): 1, (2, 9): 9}
    assert by_key(KEYED) == want
    assert {(r.key, r.vertex): r.component for r in keyed.components_by_key(edges).collect()} == want
    spark.udtf.register("star_merge", keyed.star_merge)
    edges.createOrReplaceTempView("keyed_edges")
    rows = spark.sql("SELECT * FROM star_merge(TABLE(keyed_edges) PARTITION BY key)").collect()
    assert {(r.key, r.vertex): r.component for r in rows} == want
    assert keyed.components_by_key(edges.limit(0)).count() == 0


def test_state_of_a_key_follows_the_stream(spark, tmp_path):
    for k in range(3):
        spark.createDataFrame(KEYED[3 * k:3 * k + 3], "key long, a long, b long").coalesce(1).write.parquet(str(tmp_path / "in" / f"k{k}"))
    rows = spark.readStream.schema("key long, a long, b long").option("maxFilesPerTrigger", 1).option("recursiveFileLookup", "true").parquet(str(tmp_path / "in"))
    for idle, name, trigger in ((None, "kept", {"availableNow": True}), (3_600_000, "timed", {"once": True})):
        q = keyed_components(rows, idle).writeStream.format("memory").queryName(name).outputMode("update").option("checkpointLocation", str(tmp_path / name)).trigger(**trigger).start()
        assert q.awaitTermination(60)
        last = {(r.key, r.vertex): r.component for r in spark.table(name).groupBy("key", "vertex").agg(F.min("component").alias("component")).collect()}
        assert last == by_key(KEYED)


def test_relabel_orders(spark):
    path = G.from_pairs(spark, [(1, 2), (2, 3), (2, 9)])
    new = lambda how: {r.vertex: r.new for r in G.relabel(path, how)[1].collect()}
    assert new("reverse") == {9: 0, 3: 1, 2: 2, 1: 3} and new("degree") == {2: 0, 1: 1, 3: 2, 9: 3}
    assert sorted(new("shuffle").values()) == [0, 1, 2, 3]


def test_helpers(spark):
    a = spark.createDataFrame([(1, 1), (2, 1), (3, 3)], "vertex long, component long")
    b = spark.createDataFrame([(1, 1), (2, 2), (4, 4)], "vertex long, component long")
    assert sorted(map(tuple, M.symmetric_difference(a, b).collect())) == [(2, 1), (2, 2), (3, 3), (4, 4)]
    assert found(M.component_filter(a, 2)) == {1: 1, 2: 1}
    assert [(r.n, r.vertices_reached) for r in M.coverage(a).orderBy("size_rank").collect()] == [(2, 2), (1, 3)]
    odd = spark.createDataFrame([(1, "x", 7), (2, "y", 8), (5, None, None)], "doc_id long, _c string, component long")
    assert sorted(map(tuple, M.attach_components(odd, "doc_id", a).select("doc_id", "_c", "component").collect())) == [(1, "x", 1), (2, "y", 1), (5, None, 5)]
    chain = G.from_pairs(spark, [(k, k + 1) for k in range(6)])
    assert set(found(B.recursive_sql(chain, 6)).values()) == {0} and found(B.recursive_sql(chain, 2))[6] == 4
    dense = G.from_pairs(spark, [(x, y) for x in range(12) for y in range(x)])
    assert B.local_forest(dense.coalesce(1)).count() == 11
    assert M.profile(G.from_pairs(spark, [(0, 1), (1, 2), (2, 3)])) == {"n": 4, "m": 3, "diameter": 3}


def test_entry_works_without_the_optional_folders(monkeypatch):
    import __spark_entry__ as entry

    for name in [m for m in sys.modules if m == "corpus_pipeline" or m.startswith("starfold.llm")]:
        monkeypatch.delitem(sys.modules, name)
    monkeypatch.setitem(sys.modules, "corpus_pipeline", None)
    assert "cc_retire" in entry.queries() and "pipeline" not in entry.queries()


def test_a_cluster_needs_a_shared_folder():
    from types import SimpleNamespace

    from starfold.session import ensure_checkpoint_dir

    held = SimpleNamespace(isDefined=lambda: False)
    jvm = SimpleNamespace(sc=lambda: SimpleNamespace(getCheckpointDir=lambda: held))
    fake = SimpleNamespace(conf=SimpleNamespace(get=lambda k, d: d), sparkContext=SimpleNamespace(_jsc=jvm, master="local-cluster[3,2,1000]"))
    with pytest.raises(RuntimeError, match="share"):
        ensure_checkpoint_dir(fake)


def agrees_with_sql(spark, folder, query):
    import duckdb
    from starfold import queries

    con = duckdb.connect()
    for f in folder.iterdir():
        con.execute(f"CREATE VIEW {f.stem} AS SELECT * FROM read_parquet('{f}/*.parquet')")
    want = sorted(con.execute(queries.ORACLES[query]).fetchall())
    assert sorted(map(tuple, queries.QUERIES[query](spark, str(folder)).collect())) == want
    return dict(want)


def test_recursive_sql_walks_a_given_table(spark, tmp_path):
    spark.createDataFrame([(0, 1), (1, 1), (2, 0), (3, None)], "n_nationkey int, n_regionkey int").write.parquet(str(tmp_path / "nation.parquet"))
    spark.createDataFrame([(7, 0), (8, 1), (9, 2), (10, 2), (11, 40), (12, None), (7, 0)], "c_custkey long, c_nationkey int").write.parquet(str(tmp_path / "customer.parquet"))
    got = agrees_with_sql(spark, tmp_path, "baseline_recursive_sql")
    assert got[7] == got[8] == 1 - 2_000_000 and got[9] == got[10] == -2_000_000 and got[11] == 40 - 1_000_000


def test_four_paths_take_every_order_from_a_given_table(spark, tmp_path):
    from starfold.sources import tables

    keys = [*range(96), 100, 101, 102, 105, 106, 110, -3, -2, None, 7]
    spark.createDataFrame([(k,) for k in keys], "c_custkey long").write.parquet(str(tmp_path / "customer.parquet"))
    got = agrees_with_sql(spark, tmp_path, "four_path_labels")
    assert len(got) == 96 + 3 + 2 + 2 and all(got[v] == v - v % 4 for v in range(96))
    steps = {(r.a, r.b) for r in tables.four_paths(spark, str(tmp_path)).where("a between 0 and 95").collect()}
    paths = {frozenset((a % 4, b % 4) for a, b in steps if a // 4 == g) for g in range(24)}
    assert len(steps) == 72 and len(paths) == 12
