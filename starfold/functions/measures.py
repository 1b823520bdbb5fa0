"""Cost and accuracy measures over runs and traces."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from starfold.operators import alternating, baselines, paired
from starfold.plans.loop import ComponentResult
from starfold.sources import graphs

PHI = (1 + math.sqrt(5)) / 2


def predicted_path_steps(n: int) -> int:
    """log of n to the golden ratio, rounded."""
    return round(math.log(n) / math.log(PHI))


def profile(edges: DataFrame) -> dict:
    """n, m and a two-sweep lower bound of the diameter (exact on trees)."""
    e = graphs.normalize_edges(edges)
    m = e.count()
    n = graphs.vertices_of(e).count()
    if not m:
        return {"n": 0, "m": 0, "diameter": 0}
    first = e.agg(F.min("a")).first()[0]
    far, _ = _sweep(e, first)
    _, depth = _sweep(e, far)
    return {"n": n, "m": m, "diameter": depth}


def _sweep(edges: DataFrame, start: int) -> tuple[int, int]:
    from starfold.plans.loop import materialize

    both = materialize(graphs.twins(edges))
    spark = edges.sparkSession
    seen = spark.createDataFrame([(start, 0)], "vertex long, depth int")
    front, depth, last = seen, 0, start
    while True:
        nxt = both.join(front, both.src == front.vertex).select(F.col("dst").alias("vertex")).distinct().join(seen, "vertex", "left_anti").withColumn("depth", F.lit(depth + 1))
        nxt = materialize(nxt)
        far = nxt.agg(F.min("vertex")).first()[0]
        if far is None:
            return last, depth
        last, depth = far, depth + 1
        seen, front = materialize(seen.unionByName(nxt)), nxt


def disagreement(a: DataFrame, b: DataFrame) -> int:
    """Vertices on which two labelings differ, missing ones included."""
    both = a.join(b.withColumnRenamed("component", "other"), "vertex", "full")
    return both.where(~F.col("component").eqNullSafe(F.col("other"))).count()


def growth(results: list[tuple[int, int, ComponentResult]]) -> list[dict]:
    """For (n, m, result): steps, work and communication against the bounds of the models."""
    out = []
    for n, m, r in results:
        log = max(1.0, math.log2(n))
        work = sum(x["edges_in"] or 0 for x in r.metrics)
        comm = sum((x.get("edges_mid") or 0) + (x["edges_out"] or 0) for x in r.metrics)
        out.append({"n": n, "m": m, "steps": r.n_steps, "steps_per_log": r.n_steps / log, "work_per_mlog": work / (m * log), "comm_per_mlog": comm / (m * log), "passes": r.passes})
    return out


def label_gap(trace: DataFrame) -> DataFrame:
    """vertex - label after each step of a trace on a sequential path."""
    return trace.where("dst is null").select("step", F.col("src").alias("vertex"), "label", (F.col("src") - F.col("label")).alias("gap"))


def label_retention(edges: DataFrame, max_steps: int = 200, dedupe: str = "none") -> DataFrame:
    """For every (vertex, label) pair that appears as an edge: first and last step of the unfiltered form."""
    out = paired.connected_components(edges, dedupe=dedupe, max_steps=max_steps, trace=True)
    parts = [h.select(F.lit(i).alias("step"), "src", "dst").where("dst < src").distinct() for i, h in enumerate(out.history)]
    whole = parts[0]
    for p in parts[1:]:
        whole = whole.unionByName(p)
    return whole.groupBy(F.col("src").alias("vertex"), F.col("dst").alias("label")).agg(F.min("step").alias("first_step"), F.max("step").alias("last_step"), F.count("*").alias("n_steps"))


def check_invariants(trace: DataFrame, m: int) -> DataFrame:
    """Per step: edges kept (2m), loops, and labels that rose since the step before."""
    edges = trace.where("dst is not null").groupBy("step").agg(F.sum("mult").alias("edges"), F.count_if(F.col("src") == F.col("dst")).alias("loops"))
    w = Window.partitionBy("src").orderBy("step")
    rose = trace.where("dst is null").withColumn("was", F.lag("label").over(w)).groupBy("step").agg(F.count_if(F.col("label") > F.col("was")).alias("rose"))
    return edges.join(rose, "step").select("step", "edges", (F.col("edges") == 2 * m).alias("constant"), "loops", "rose")


def largest_key(edges: DataFrame) -> dict:
    """Rows of the biggest source, of all sources and of those that act."""
    both = graphs.twins(graphs.normalize_edges(edges))
    sizes = both.groupBy("src").agg(F.count("*").alias("n"), F.min("dst").alias("least"))
    row = sizes.agg(F.max("n").alias("all"), F.max(F.when(F.col("least") < F.col("src"), F.col("n"))).alias("acting")).first()
    return {"max_key_rows": row["all"], "max_acting_key_rows": row["acting"]}


METHODS = {
    "alternating": alternating.connected_components,
    "alternating_tree": lambda e: alternating.connected_components(e, combine="tree"),
    "alternating_retire": lambda e: alternating.connected_components(e, retire=True),
    "paired": paired.connected_components,
    "paired_within_step": lambda e: paired.connected_components(e, dedupe="within_step"),
    "paired_none": lambda e: paired.connected_components(e, dedupe="none"),
    "sorted": paired.sorted_components,
    "sorted_none": lambda e: paired.sorted_components(e, dedupe="none"),
    "min_flood": baselines.min_flood,
    "duplicating_flood": baselines.duplicating_flood,
    "hook_compress": baselines.hook_and_compress,
    "hook_compress_tree": lambda e: baselines.hook_and_compress(e, full_compress=True, combine="tree"),
    "coin_flip": baselines.coin_flip_contraction,
    "sort_random": baselines.sort_random_contraction,
    "two_star": baselines.two_star_rounds,
}


def compare(edges: DataFrame, names: list[str] | None = None) -> list[dict]:
    """One row a method: steps, passes, work, largest edge set against 2m, seconds and components."""
    m2 = 2 * graphs.normalize_edges(edges).count()
    out = []
    for name in names or METHODS:
        r = METHODS[name](edges)
        peak = max((x.get("edges_out") or 0 for x in r.metrics), default=0)
        out.append({
            "method": name, "steps": r.n_steps, "passes": r.passes, "work": sum(x["edges_in"] or 0 for x in r.metrics),
            "dup_factor": peak / m2 if m2 else 0.0, "seconds": sum(x["elapsed_ms"] for x in r.metrics) / 1000,
            "components": r.whole().select("component").distinct().count(),
        })
    return out


def component_sizes(labels: DataFrame) -> DataFrame:
    return labels.groupBy("component").agg(F.count("*").alias("n"))


def size_histogram(labels: DataFrame) -> DataFrame:
    return component_sizes(labels).groupBy("n").agg(F.count("*").alias("components"))


def largest_components(labels: DataFrame, k: int) -> DataFrame:
    return component_sizes(labels).orderBy(F.desc("n"), "component").limit(k)


def component_filter(labels: DataFrame, least: int = 1, most: int | None = None) -> DataFrame:
    """Labels of components of ``least`` to ``most`` vertices."""
    size = F.col("n") >= least
    sizes = component_sizes(labels).where(size if most is None else size & (F.col("n") <= most))
    return labels.join(sizes.select("component"), "component", "left_semi").select("vertex", "component")


def coverage(labels: DataFrame) -> DataFrame:
    """Share of all vertices in the components of each size and above; one row a size, so the window holds few rows."""
    sizes = size_histogram(labels)
    larger = Window.orderBy(F.desc("n")).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    reach = F.sum(F.col("n") * F.col("components"))
    return sizes.select("n", "components", F.dense_rank().over(Window.orderBy(F.desc("n"))).cast("long").alias("size_rank"), reach.over(larger).alias("vertices_reached"))


def edge_delta(trace: DataFrame, k: int) -> DataFrame:
    """Edges that step ``k`` of a trace made (change 1) or took away (change -1), with repeats."""
    at = lambda n: trace.where((F.col("step") == n) & F.col("dst").isNotNull()).select("src", "dst", F.explode(F.sequence(F.lit(1).cast("long"), "mult"))).select("src", "dst")
    was, now = at(k - 1), at(k)
    return now.exceptAll(was).withColumn("change", F.lit(1)).unionByName(was.exceptAll(now).withColumn("change", F.lit(-1)))


def symmetric_difference(a: DataFrame, b: DataFrame) -> DataFrame:
    """(vertex, component) pairs that one of two labelings has and the other lacks."""
    pair = ["vertex", "component"]
    x, y = a.select(*pair), b.select(*pair)
    return x.exceptAll(y).unionByName(y.exceptAll(x))


def attach_components(df: DataFrame, key: str, labels: DataFrame) -> DataFrame:
    """``df`` with the component of ``key``; a key that no edge names is its own component. A column ``component`` of ``df`` is replaced."""
    rows = df.select(F.struct("*").alias("row"), F.col(key).alias("vertex"))
    named = rows.join(labels.select("vertex", "component"), "vertex", "left")
    kept = [F.col(f"row.`{c}`") for c in df.columns if c != "component"]
    return named.select(*kept, F.coalesce("component", "vertex").alias("component"))


def model_costs(spark: SparkSession, edges: DataFrame, names: list[str]) -> DataFrame:
    """Steps, passes, work and duplication of each method: counts alone, which do not depend on the machine."""
    rows = [(r["method"], r["steps"], r["passes"], r["work"], round(r["dup_factor"], 6), r["components"]) for r in compare(edges, names)]
    return spark.createDataFrame(rows, "method string, steps long, passes long, work long, dup_factor double, components long")
