"""Comparators. Only their family and cost are given by the reference; the inner steps follow public literature."""

from __future__ import annotations

import functools
import itertools
import time

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from starfold.operators import packed
from starfold.operators.alternating import add_isolated
from starfold.plans.loop import ComponentResult, brief_shuffles, discard, materialize, setting, tidy
from starfold.sources.graphs import encode_vertices, normalize_edges, twins, vertices_of

#: Directed edges of a slice of the flood at its start; they grow about tenfold on the order-part graph.
SLICE_ROWS = 250_000
INTEGERS = ("tinyint", "smallint", "int", "bigint")


def _row(k: int, edges: int | None, lowered: int, began: float) -> dict:
    return {"step": k, "edges_in": edges, "edges_out": edges, "lowered": lowered, "mismatched": lowered, "active": lowered, "elapsed_ms": (time.monotonic() - began) * 1000}


@tidy
def min_flood(edges: DataFrame, *, vertices: DataFrame | None = None, max_steps: int | None = None) -> ComponentResult:
    """Each vertex takes the least label among its neighbours, one hop a round, until nothing changes or for ``max_steps``."""
    both = materialize(twins(normalize_edges(edges)))
    size = both.count()
    labels = table = materialize(both.select(F.col("src").alias("vertex")).distinct().select("vertex", F.col("vertex").alias("component")))
    metrics, converged = [], False
    for k in itertools.count(1) if max_steps is None else range(1, max_steps + 1):
        began = time.monotonic()
        met = both.join(labels, both.dst == labels.vertex).groupBy("src").agg(F.min("component").alias("near"))
        nxt = labels.join(met, labels.vertex == met.src, "left").select("vertex", F.least("component", "near").alias("component"), (F.col("near") < F.col("component")).alias("fell"))
        nxt = materialize(nxt, [F.count_if("fell").alias("fell")])
        fell = nxt.measured["fell"]
        discard(table)
        table, labels = nxt, nxt.select("vertex", "component")
        metrics.append(_row(k, size, fell, began))
        if fell == 0:
            converged = True
            break
    return ComponentResult(add_isolated(labels, vertices), metrics, None, converged, keep=[table])


@tidy
def duplicating_flood(
    edges: DataFrame, *, vertices: DataFrame | None = None, max_steps: int | None = None, max_edges: int | None = None, slice_rows: int = SLICE_ROWS,
) -> ComponentResult:
    """Adds (u, l(v)) and keeps every old edge, so that the edge count grows. Stops at a given ``max_steps`` or ``max_edges``, not converged.

    A step hands on what earlier steps have not: a label that fell to all neighbours, another to neighbours just met.
    Edges are only appended. They lie packed in slices by their source, at first of about ``slice_rows`` each, those to
    smaller vertices apart from their twins; a task sorts what is told to its slice together with these.
    """
    types = {t for _, t in edges.select("a", "b").dtypes}
    if not types <= set(INTEGERS):
        return _flood_of_names(edges, vertices, max_steps=max_steps, max_edges=max_edges, slice_rows=slice_rows)
    plain = edges.where("a <> b").select(F.greatest("a", "b").cast("long").alias("src"), F.least("a", "b").cast("long").alias("dst"))
    plain = materialize(plain, [F.count("*").alias("n")])
    slots = max(1, -(-2 * plain.measured["n"] // slice_rows))
    packed_by = lambda df, step: df.mapInArrow(step, packed.SCHEMA)
    gathered = lambda *parts: functools.reduce(DataFrame.union, parts).repartitionById(slots, F.col("slot"))
    of = lambda t, kind, as_kind=None: t.where(F.col("kind") == kind).select(F.lit(as_kind or kind).alias("kind"), "slot", "n", "pairs")
    pairs = lambda df: df.mapInArrow(packed.spread, "src long, dst long").select(*[F.col(c).cast(max(types, key=INTEGERS.index)) for c in ("src", "dst")])
    edge_count = [F.coalesce(F.sum("n"), F.lit(0)).alias("n")]
    metrics, converged = [], False
    with brief_shuffles(edges.sparkSession):
        added = materialize(packed_by(gathered(packed_by(plain, packed.placing(slots))), packed.merging(slots)), edge_count, by="kind")
        discard(plain)
        known, labels, size = [added], [], added.measured["n"]
        for k in itertools.count(1) if max_steps is None else range(1, max_steps + 1):
            began = time.monotonic()
            rows = [of(t, kind, f"fresh_{kind}" if t is added else kind) for t in known for kind in ("down", "up")]
            told = materialize(packed_by(gathered(*rows, *labels), packed.telling(slots)), by="kind")
            new = gathered(of(told, "told"), *[of(t, "down") for t in known])
            added = materialize(packed_by(new, packed.merging(slots)), edge_count, by="kind")
            labels, was = [materialize(of(told, "labels"))], labels
            discard(told, *was)
            known.append(added)
            now = size + added.measured["n"]
            metrics.append(_row(k, size, now - size, began) | {"edges_out": now})
            same, size = now == size, now
            if same:
                converged = True
                break
            if max_edges is not None and now > max_edges:
                break
    parts = [pairs(t) for t in known]
    whole = functools.reduce(DataFrame.union, parts)
    if converged:
        found = pairs(labels[0]).select(F.col("src").alias("vertex"), F.col("dst").alias("component"))
    else:
        found = whole.groupBy("src").agg(F.min("dst").alias("m")).select(F.col("src").alias("vertex"), F.least("src", "m").alias("component"))
    return ComponentResult(add_isolated(found, vertices), metrics, whole, converged, keep=[*parts, *known, *labels])


def _flood_of_names(edges: DataFrame, vertices: DataFrame | None, **options) -> ComponentResult:
    """The flood over vertices of another type than whole numbers, by numbers that keep their order."""
    coded, names = encode_vertices(edges.where("a <> b"), "a", "b")
    names = materialize(names)
    named = lambda df: functools.reduce(
        lambda d, c: d.join(names.select(F.col("vertex").alias(c), F.col("key").alias(f"{c}_key")), c).drop(c).withColumnRenamed(f"{c}_key", c), df.columns, df,
    ).select(*df.columns)
    out = duplicating_flood(coded, **options)
    return ComponentResult(add_isolated(named(out.labels), vertices), out.metrics, named(out.edges), out.converged, keep=[names, *out.keep])


@tidy
def hook_and_compress(edges: DataFrame, *, vertices: DataFrame | None = None, full_compress: bool = False, combine: str = "partial", salts: int = 8, max_steps: int = 200) -> ComponentResult:
    """Hook the larger parent under the least parent met, then replace parents by grandparents."""
    e = materialize(normalize_edges(edges))
    size = 2 * e.count()
    parent = materialize(vertices_of(e).select("vertex", F.col("vertex").alias("p")))
    metrics, converged = [], False
    for k in range(1, max_steps + 1):
        began = time.monotonic()
        pa = parent.select(F.col("vertex").alias("a"), F.col("p").alias("pa"))
        pb = parent.select(F.col("vertex").alias("b"), F.col("p").alias("pb"))
        met = e.join(pa, "a").join(pb, "b").where("pa <> pb").select(F.greatest("pa", "pb").alias("hi"), F.least("pa", "pb").alias("lo"))
        if combine == "tree":
            width = salts
            met = met.withColumn("salt", F.pmod(F.hash("lo"), F.lit(salts)))
            while width > 1:
                met = met.groupBy("hi", "salt").agg(F.min("lo").alias("lo")).withColumn("salt", F.floor(F.col("salt") / 2).cast("int"))
                width = -(-width // 2)
        hooks = met.groupBy("hi").agg(F.min("lo").alias("lo"))
        hooked = parent.join(hooks, parent.vertex == hooks.hi, "left").select("vertex", F.least("p", F.coalesce("lo", "p")).alias("p"), F.col("p").alias("was"))
        hooked = materialize(hooked)
        while True:
            up = hooked.select(F.col("vertex").alias("p"), F.col("p").alias("gp"))
            jumped = materialize(hooked.join(up, "p").select("vertex", F.least("p", "gp").alias("p"), "was", (F.col("gp") < F.col("p")).alias("moved")))
            moved = jumped.where("moved").count() if full_compress else 0
            hooked = jumped.select("vertex", "p", "was")
            if not moved:
                break
        changed = hooked.where("p <> was").count()
        discard(parent)
        parent = materialize(hooked.select("vertex", "p"))
        discard(jumped)
        metrics.append(_row(k, size, changed, began))
        if changed == 0:
            converged = True
            break
    labels = parent.select("vertex", F.col("p").alias("component"))
    return ComponentResult(add_isolated(labels, vertices), metrics, None, converged, keep=[parent])


@tidy
def coin_flip_contraction(edges: DataFrame, *, vertices: DataFrame | None = None, seed: int = 1, max_steps: int = 200, sort: bool = False) -> ComponentResult:
    """Seeded leader contraction: a follower joins its least leader neighbour; renamed loops and repeats vanish."""
    live = materialize(normalize_edges(edges))
    names = materialize(vertices_of(live).select("vertex", F.col("vertex").alias("c")))
    metrics, size = [], live.count()
    for k in range(1, max_steps + 1):
        if size == 0:
            break
        began = time.monotonic()
        head = lambda c, k=k: F.pmod(F.xxhash64(F.col(c), F.lit(seed), F.lit(k)), F.lit(2)) == 1
        both = twins(live)
        if sort:
            both = both.repartitionByRange("src").sortWithinPartitions("src", "dst")
        join = both.where(~head("src") & head("dst")).groupBy("src").agg(F.min("dst").alias("to"))
        join = materialize(join)
        to = lambda c: join.select(F.col("src").alias(c), F.col("to").alias(f"{c}_to"))
        names = materialize(names.join(to("c"), "c", "left").select("vertex", F.coalesce("c_to", "c").alias("c")))
        moved = live.join(to("a"), "a", "left").join(to("b"), "b", "left").select(F.coalesce("a_to", "a").alias("a"), F.coalesce("b_to", "b").alias("b"))
        live = materialize(normalize_edges(moved))
        left = live.count()
        metrics.append(_row(k, 2 * size, size - left, began) | {"edges_out": 2 * left})
        size = left
    least = names.groupBy("c").agg(F.min("vertex").alias("component"))
    labels = names.join(least, "c").select("vertex", "component")
    return ComponentResult(add_isolated(labels, vertices), metrics, None, size == 0, 2 if sort else 1, keep=[names])


def sort_random_contraction(edges: DataFrame, *, vertices: DataFrame | None = None, seed: int = 1) -> ComponentResult:
    """The contraction evaluated by sorted passes; ``passes`` counts them."""
    return coin_flip_contraction(edges, vertices=vertices, seed=seed, sort=True)


@tidy
def two_star_rounds(edges: DataFrame, *, vertices: DataFrame | None = None, max_steps: int = 200) -> ComponentResult:
    """Alternate two re-attachments: larger neighbours to the closed minimum, then smaller ones to the least of them."""
    e = materialize(normalize_edges(edges))
    size, metrics, converged = e.count(), [], False
    for k in range(1, max_steps + 1):
        began = time.monotonic()
        both = twins(e)
        low = both.groupBy("src").agg(F.min("dst").alias("m")).select("src", F.least("src", "m").alias("m"))
        large = normalize_edges(both.join(low, "src").where("dst > src").select(F.col("dst").alias("a"), F.col("m").alias("b")))
        least = large.groupBy("b").agg(F.min("a").alias("m"))
        small = large.join(least, "b")
        nxt = normalize_edges(small.select(F.explode(F.array(F.struct("a", F.col("m").alias("b")), F.struct(F.col("b").alias("a"), F.col("m").alias("b")))).alias("e")).select("e.*"))
        nxt = materialize(nxt)
        now = nxt.count()
        changed = nxt.exceptAll(e).count() if now == size else 1
        metrics.append(_row(k, 2 * size, changed, began) | {"edges_out": 2 * now})
        e, size = nxt, now
        if changed == 0:
            converged = True
            break
    stars = e.select(F.col("b").alias("vertex"), F.col("a").alias("component"))
    labels = stars.unionByName(e.select(F.col("a").alias("vertex"), F.col("a").alias("component")).distinct())
    labels = labels.groupBy("vertex").agg(F.min("component").alias("component"))
    return ComponentResult(add_isolated(labels, vertices), metrics, e, converged, 2, keep=[e])


def recursive_sql(edges: DataFrame, depth: int) -> DataFrame:
    """Labels by a recursive query that walks at most ``depth`` hops; right if no vertex lies farther from its least one.

    Only walks over larger vertices than their start are followed: from the least vertex of a component all are.
    Spark ends recursions of more than a million rows with an error unless it is told not to.
    """
    spark = edges.sparkSession
    twins(normalize_edges(edges)).createOrReplaceTempView("starfold_twins")
    with setting(spark, "spark.sql.cteRecursionRowLimit", "-1"):
        return materialize(spark.sql(f"""
        WITH RECURSIVE walk(vertex, component, depth) AS (
            SELECT DISTINCT src, src, 0 FROM starfold_twins
            UNION ALL
            SELECT t.dst, w.component, w.depth + 1 FROM walk w JOIN starfold_twins t ON t.src = w.vertex
            WHERE w.depth < {int(depth)} AND t.dst > w.component)
        SELECT vertex, min(component) AS component FROM walk GROUP BY vertex"""))


def local_forest(edges: DataFrame) -> DataFrame:
    """A spanning forest of the edges of each task: the same components from at most one edge a vertex and task.

    The state of a task is one entry a vertex it meets, so tasks should be of a size that an executor can hold.
    """
    def step(batches):
        up: dict[int, int] = {}

        def root(x: int) -> int:
            while up.setdefault(x, x) != x:
                up[x] = up[up[x]]
                x = up[x]
            return x

        for batch in batches:
            a, b = [], []
            for x, y in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                p, q = root(x), root(y)
                if p != q:
                    up[max(p, q)] = min(p, q)
                    a.append(x)
                    b.append(y)
            yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], ["a", "b"])

    return edges.where("a is not null and b is not null").select("a", "b").mapInArrow(step, "a bigint, b bigint")


def union_find(edges: DataFrame, limit: int = 2_000_000) -> dict[int, int]:
    """Exact answer on the driver for small graphs; refuses more than ``limit`` edges."""
    rows = edges.select("a", "b").where("a is not null and b is not null").limit(limit + 1).collect()
    if len(rows) > limit:
        raise ValueError(f"more than {limit} edges")
    up: dict[int, int] = {}

    def root(x: int) -> int:
        while up.setdefault(x, x) != x:
            up[x] = up[up[x]]
            x = up[x]
        return x

    for a, b in rows:
        x, y = root(a), root(b)
        if x != y:
            up[max(x, y)] = min(x, y)
    return {v: root(v) for v in list(up)}
