"""Every method on every small graph, the retiring rule, plans, layouts and clean-up."""

import itertools

import numpy as np
import pytest
from pyspark.sql import functions as F

from starfold.functions import measures
from starfold.operators import alternating as A
from starfold.operators import baselines as B
from starfold.operators import paired
from starfold.sources import graphs as G

#: A class that leaves while a message of its own still meets another class gives vertex 10 the component 1.
LATE_MESSAGE = [(0, 6), (0, 7), (1, 2), (1, 3), (2, 5), (3, 6), (3, 8), (4, 9), (4, 10), (4, 12), (5, 10), (6, 9), (7, 8)]


def labels(r):
    return {x.vertex: x.component for x in r.labels.collect()}


def answer(pairs):
    up = {}

    def root(x):
        while up.setdefault(x, x) != x:
            x = up[x]
        return x

    for a, b in pairs:
        x, y = root(a), root(b)
        up[max(x, y)] = min(x, y)
    return {v: root(v) for v in up}


def small_graphs():
    """All graphs on up to five vertices, and 500 random ones on up to 14."""
    for n in range(2, 6):
        sides = list(itertools.combinations(range(n), 2))
        for mask in range(1, 1 << len(sides)):
            yield [s for k, s in enumerate(sides) if mask >> k & 1]
    rng = np.random.default_rng(8)
    for _ in range(500):
        n = int(rng.integers(6, 15))
        sides = np.array(list(itertools.combinations(range(n), 2)))
        yield [tuple(map(int, s)) for s in sides[rng.random(len(sides)) < rng.uniform(0.1, 0.4)]]


@pytest.fixture(scope="module")
def union(spark):
    pairs = [(20 * i + a, 20 * i + b) for i, g in enumerate(small_graphs()) for a, b in g]
    return G.from_pairs(spark, pairs).repartition(4).cache(), answer(pairs)


@pytest.mark.parametrize("name", sorted(measures.METHODS))
def test_every_small_graph(union, name):
    r = measures.METHODS[name](union[0])
    assert r.converged and labels(r) == union[1]


def test_retiring_waits_for_late_messages(spark):
    r = A.connected_components(G.from_pairs(spark, LATE_MESSAGE), retire=True)
    assert r.converged and labels(r) == answer(LATE_MESSAGE)


def simulate(pairs):
    """The retiring rule on plain sets, with a check that a class that leaves is a whole component."""
    edges = {(a, b) for a, b in pairs} | {(b, a) for a, b in pairs}
    label = {v: min([v, *[b for a, b in edges if a == v]]) for v in {v for e in edges for v in e}}
    done = {}
    while edges:
        off, fresh, nxt = set(), dict(label), set()
        for v, u in edges:
            nxt.add((u, label[v]) if u != label[v] else (u, v))
            fresh[u] = min(fresh[u], label[v])
            if label[v] != label[u]:
                off |= {label[v], label[u]}
        for v in label:
            if fresh[v] != label[v]:
                off |= {fresh[v], label[v]}
        done |= {v: c for v, c in fresh.items() if c not in off}
        edges = {(a, b) for a, b in nxt if fresh[a] in off}
        label = {v: c for v, c in fresh.items() if c in off}
    return done | label


def test_retiring_rule_on_plain_sets():
    rng = np.random.default_rng(3)
    for _ in range(4000):
        n = int(rng.integers(4, 14))
        sides = np.array(list(itertools.combinations(range(n), 2)))
        pairs = [tuple(map(int, s)) for s in sides[rng.random(len(sides)) < rng.uniform(0.1, 0.35)]]
        assert simulate(pairs) == answer(pairs)


@pytest.mark.parametrize("hub_rows", [0, 40])
def test_a_hub_switches_the_layout(spark, hub_rows):
    star = [(0, i) for i in range(1, 120)] + [(200 + i, 201 + i) for i in range(9)] + [(119, 200)]
    r = A.connected_components(G.from_pairs(spark, star), hub_rows=hub_rows)
    assert labels(r) == answer(star) and r.metrics[-1]["layout"] == "spread" and r.metrics[0]["largest_key"] >= 100


def test_steps_do_not_depend_on_partitions(spark):
    """The number of steps is a property of the graph: the same for any number of tasks."""
    e = G.seq_path(spark, 7)
    held = spark.conf.get("spark.sql.shuffle.partitions")
    try:
        found = set()
        for n in (1, 3, 8):
            spark.conf.set("spark.sql.shuffle.partitions", str(n))
            r = A.connected_components(e.repartition(n), stop="quiet_counter")
            found.add((r.n_steps, tuple(m["edges_mid"] for m in r.metrics)))
        assert len(found) == 1
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", held)


def test_hot_step_has_one_exchange(spark):
    from starfold.plans.loop import materialize

    state = materialize(A._initial(G.twins(G.seq_path(spark, 6))))
    plan = A._step("compact", 0, 4)(state)._jdf.queryExecution()
    text = plan.executedPlan().toString()
    assert text.count("Exchange hashpartitioning") == 1 and "Join" not in text and "Python" not in text
    spread = A._step("spread", 2, 8)(state)._jdf.queryExecution().executedPlan().toString()
    assert "Window" not in spread and "Python" not in spread


def tables(spark):
    from starfold.session import ensure_checkpoint_dir

    sc = spark.sparkContext
    at = sc._jvm.org.apache.hadoop.fs.Path(f"{ensure_checkpoint_dir(spark)}/starfold-{sc.applicationId}")
    fs = at.getFileSystem(sc._jsc.hadoopConfiguration())
    return {str(f.getPath()) for f in fs.listStatus(at)} if fs.exists(at) else set()


@pytest.mark.parametrize("name", ["alternating", "alternating_tree", "alternating_retire", "paired", "sorted", "min_flood", "duplicating_flood", "hook_compress", "coin_flip", "two_star"])
def test_runs_leave_only_what_the_result_reads(spark, name):
    before = tables(spark)
    r = measures.METHODS[name](G.from_pairs(spark, LATE_MESSAGE))
    left = tables(spark) - before
    assert labels(r) == answer(LATE_MESSAGE) and len(left) <= len(r.keep)


def test_an_error_leaves_no_table(spark):
    before = tables(spark)
    with pytest.raises(Exception):
        A.run_twins(spark.createDataFrame([(1, 2)], "src long, dst long").withColumn("dst", F.raise_error(F.lit("x")).cast("long")))
    assert tables(spark) == before


def test_sorted_form_has_the_edges_of_the_grouped_one(spark):
    e = G.from_pairs(spark, LATE_MESSAGE)
    for mode in paired.MODES:
        a, b = paired.connected_components(e, dedupe=mode, trace=True), paired.sorted_components(e, dedupe=mode, trace=True)
        assert [sorted(map(tuple, h.collect())) for h in a.history] == [sorted(map(tuple, h.collect())) for h in b.history]
        cost = ("edges_in", "edges_mid", "edges_out", "propagated", "dups_within", "dups_across")
        assert [[m[c] for c in cost] for m in a.metrics] == [[m[c] for c in cost] for m in b.metrics]


def test_scans_carry_over_batches(spark):
    """Batches of one row give the same as one batch: all that is needed is carried."""
    import pyarrow as pa

    rng = np.random.default_rng(1)
    rows = sorted({(int(a), int(b)) for a, b in rng.integers(0, 9, (40, 2)) if a != b})
    whole = pa.RecordBatch.from_pydict({"src": [a for a, _ in rows], "dst": [b for _, b in rows]})
    flat = lambda it: sorted((*r.values(),) for b in it for r in b.to_pylist())
    assert flat(paired.scan_sources([whole])) == flat(paired.scan_sources([whole.slice(k, 1) for k in range(len(rows))]))
    marked = sorted(flat(paired.scan_sources([whole])), key=lambda r: (r[0], r[1], not r[2]))
    batch = pa.RecordBatch.from_pydict({"src": [r[0] for r in marked], "dst": [r[1] for r in marked], "is_old": [r[2] for r in marked]})
    want = sorted((a, b, any(r == (a, b, True) for r in marked)) for a, b in {r[:2] for r in marked if not r[2]})
    assert flat(paired.scan_neighbours([batch])) == want == flat(paired.scan_neighbours([batch.slice(k, 1) for k in range(len(marked))]))
