import inspect

import pytest
from pyspark.sql import functions as F

from starfold.functions import measures
from starfold.operators import alternating as A
from starfold.operators import baselines as B
from starfold.operators import incremental, paired
from starfold.sources import graphs as G

SMALL = [(0, 1), (1, 2), (2, 3), (10, 11), (11, 12), (10, 12), (20, 25), (21, 25), (22, 25), (23, 25), (30, 31), (5, 3)]


def labels(r):
    return {x.vertex: x.component for x in r.labels.collect()}


@pytest.mark.parametrize("name", sorted(measures.METHODS))
def test_every_method_agrees_with_union_find(spark, name):
    e = G.from_pairs(spark, SMALL)
    r = measures.METHODS[name](e)
    assert r.converged and labels(r) == B.union_find(e)


def test_published_step_counts(spark):
    assert A.connected_components(G.seq_path(spark, 6), stop="quiet_counter").n_steps == 11
    r = A.connected_components(G.bridged_grid(spark, 16, 4), stop="quiet_counter")
    assert r.n_steps == 6
    assert {m["edges_out"] for m in r.metrics} == {2 * (2 * 16 - 1) * 4}


def test_filtered_form_needs_more_steps_on_paths(spark):
    assert paired.connected_components(G.seq_path(spark, 6)).n_steps == 13


def test_figure_trace_labels(spark):
    t = A.trace(G.figure_path(spark), 2).where("dst is null and step = 2").collect()
    assert {(r.src, r.label) for r in t} == {(1, 1), (2, 1), (3, 1), (4, 1)}


def test_label_pause_is_unsound_and_agreement_is_not(spark):
    e = G.from_pairs(spark, [(5, 6), (0, 8), (1, 2), (1, 4), (3, 7), (3, 6), (7, 8), (2, 5), (4, 7)])
    assert set(labels(A.connected_components(e)).values()) == {0}
    assert labels(A.connected_components(e, stop="label_pause"))[6] == 1


def test_degenerate_inputs(spark):
    assert labels(A.connected_components(G.from_pairs(spark, []))) == {}
    assert labels(A.connected_components(G.from_pairs(spark, [(1, 1), (2, 2)]))) == {}
    e = spark.createDataFrame([(3, 9), (9, 3), (3, 3), (None, 4), (-5, 9)], "a long, b long")
    lone = spark.createDataFrame([(9,), (77,), (None,)], "vertex long")
    assert labels(A.connected_components(e, vertices=lone)) == {3: -5, 9: -5, -5: -5, 77: 77}


def test_cut_run_says_so(spark):
    assert not A.connected_components(G.seq_path(spark, 6), max_steps=2).converged


def test_local_only_does_not_settle(spark):
    assert paired.local_only(G.figure_path(spark), 8)[-1] > 0


def test_suppress_modes(spark):
    new = spark.createDataFrame([(1, 2), (1, 2), (3, 4)], "src long, dst long")
    old = spark.createDataFrame([(3, 4)], "src long, dst long")
    assert [paired.suppress(new, old, m).count() for m in paired.MODES] == [3, 2, 1]


def test_incremental_equals_batch(spark):
    e = G.from_pairs(spark, SMALL)
    old = A.connected_components(e.where("a % 2 = 0")).labels
    got = incremental.merge_edges(old, e.where("a % 2 = 1"))
    assert {r.vertex: r.component for r in got.collect()} == B.union_find(e)


def test_encode_keeps_order(spark):
    e = spark.createDataFrame([("b", "a"), ("c", "b"), ("x", "y")], "p string, q string")
    coded, names = G.encode_vertices(e, "p", "q", 3)
    assert [r.key for r in names.orderBy("vertex").collect()] == ["a", "b", "c", "x", "y"]
    assert coded.count() == 3


def test_hot_step_has_one_exchange_and_no_python(spark):
    state = G.twins(G.seq_path(spark, 4)).select("src", "dst", F.lit(1).cast("long").alias("mult"), F.lit(0).cast("long").alias("label"))
    plan = A._step("compact", 0, 4)(state.repartition(4))._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "CartesianProduct" not in plan


def test_flood_queries_have_no_cut_and_a_cut_run_raises(spark):
    from starfold import queries

    e = G.from_pairs(spark, SMALL)
    for method, cut in ((B.min_flood, {"max_steps": 1}), (B.duplicating_flood, {"max_edges": 5})):
        assert {p.default for n, p in inspect.signature(method).parameters.items() if n.startswith("max_")} == {None}
        with pytest.MonkeyPatch.context() as m:
            m.setitem(queries.B, "small", lambda s, d: e)
            assert {r.vertex: r.component for r in queries._labels("small", method)(spark, "").collect()} == B.union_find(e)
            with pytest.raises(RuntimeError, match="not converged"):
                queries._labels("small", lambda x, f=method, c=cut: f(x, **c))(spark, "")


@pytest.mark.parametrize("slice_rows", [1 << 20, 6])
def test_flood_only_appends_what_a_step_adds(spark, slice_rows):
    """The edges of every step are those of the plain rule, and none is written twice."""
    got = B.duplicating_flood(G.from_pairs(spark, SMALL), slice_rows=slice_rows)
    both, sizes = {(x, y) for a, b in SMALL for x, y in ((a, b), (b, a))}, []
    while not sizes or sizes[-1] != (sizes[-2] if sizes[1:] else 0):
        least = {v: min(v, *(d for s, d in both if s == v)) for v, _ in both}
        made = {(u, least[v]) for v, u in both if u != least[v]}
        both |= made | {(y, x) for x, y in made}
        sizes.append(len(both))
    assert [m["edges_out"] for m in got.metrics] == sizes
    assert sorted(map(tuple, got.edges.collect())) == sorted(both)
    assert labels(got) == B.union_find(G.from_pairs(spark, SMALL))
    written = [t for t in got.keep if "dst" in t.columns]
    assert len(written) > 1 and sum(t.count() for t in written) == len(both)
    cut = B.duplicating_flood(G.from_pairs(spark, SMALL), slice_rows=slice_rows, max_steps=1)
    assert not cut.converged and cut.edges.count() == sizes[0]


FAR = [(-(2**63), 2**63 - 1), (2**63 - 1, 5), (5, -7), (40, 41), (41, 42), (42, 40)]


def test_flood_stores_and_exchanges_slices_not_edges(spark):
    """Steps hand packed slices from task to task: tables have a row for a slice, whatever the number of its edges."""
    got = B.duplicating_flood(G.seq_path(spark, 8))
    tables = [t for t in got.keep if "dst" not in t.columns]
    assert len(tables) == got.n_steps + 2 and got.converged
    assert all(t.count() <= 2 for t in tables) and got.edges.count() == got.metrics[-1]["edges_out"] > 2000
    assert set(labels(got).values()) == {0} and len(labels(got)) == 256


@pytest.mark.parametrize("slice_rows", [1 << 20, 4])
def test_flood_takes_all_longs_other_types_and_no_edges(spark, slice_rows):
    far = G.from_pairs(spark, FAR)
    assert labels(B.duplicating_flood(far, slice_rows=slice_rows)) == B.union_find(far)
    assert labels(B.duplicating_flood(G.from_pairs(spark, []), slice_rows=slice_rows)) == {}
    small = B.duplicating_flood(far.where("a between 40 and 42").selectExpr("cast(a as int) a", "cast(b as short) b"), slice_rows=slice_rows)
    assert small.labels.schema["vertex"].dataType.simpleString() == "int" and labels(small) == {40: 40, 41: 40, 42: 40}
    names = B.duplicating_flood(spark.createDataFrame([("b", "a"), ("c", "b"), ("x", "y"), ("x", None)], "a string, b string"), slice_rows=slice_rows)
    assert labels(names) == {"a": "a", "b": "a", "c": "a", "x": "x", "y": "x"}
    assert sorted(map(tuple, names.edges.collect())) == sorted((x, y) for p in ("ab", "bc", "ac", "xy") for x, y in (p, p[::-1]))


def test_packed_pairs_equal_plain_sets():
    import numpy as np

    from starfold.operators import packed as P

    rng = np.random.default_rng(3)
    for low, high in ((0, 9), (-50, 50), (0, 2**31), (-(2**63), 2**63 - 1), (2**62, 2**63 - 1)):
        a, b, c, d = (rng.integers(low, high, 300) for _ in range(4))
        a, b = np.r_[a, a[:50], c[:20]], np.r_[b, b[:50], d[:20]]
        want = sorted(set(zip(a.tolist(), b.tolist())) - set(zip(c.tolist(), d.tolist())))
        x, y = P.unseen(a, b, (c, d))
        assert list(zip(x.tolist(), y.tolist())) == want
        rows = list(P.dealt("down", x, y, 7))
        assert sum(n for _, _, n, _ in rows) == len(want)
        back = [(v, w) for _, s, _, data in rows for v, w in zip(*(z.tolist() for z in P._all([data]))) if P.slot_of(np.array([v]), 7)[0] == s]
        assert sorted(back) == want
