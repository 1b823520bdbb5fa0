"""The principal method: every directed edge is rewritten once a step, so their number never changes.

State rows are ``(src, dst, mult, label)``: an edge with the label of its source, or, where ``dst`` is null,
the label record of a vertex. Both rewrites give an edge that starts at the old target. One exchange by the
new source therefore serves the rewriting, the label update and the stop test, and no join is needed.
"""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from starfold.plans.loop import ComponentResult, discard, materialize, tidy
from starfold.plans.stopping import rule
from starfold.sources.graphs import normalize_edges, twins

LAYOUTS = ("auto", "compact", "spread")
#: Rows of one source that one task may hold in the compact layout (about 0.3 GB).
HUB_ROWS = 4_000_000


def _largest_source(directed: DataFrame) -> int:
    """Rows of the biggest source, from a partial count: no task holds a source whole."""
    return directed.groupBy("src").count().agg(F.max("count")).first()[0] or 0


def _initial(directed: DataFrame, spread: bool = False) -> DataFrame:
    """First state: labels are the least id of each closed neighbourhood. Where ``spread``, minima are folded before the exchange and joined back, so that a hub stays in many tasks."""
    own = directed.select(F.explode(F.array("src", "dst")).alias("src")).distinct()
    rows = directed.groupBy("src", "dst").agg(F.count("*").alias("mult")).unionByName(
        own.select("src", F.lit(None).cast("long").alias("dst"), F.lit(0).cast("long").alias("mult"))
    )
    if spread:
        least = directed.groupBy("src").agg(F.min("dst").alias("least"))
        return rows.join(least, "src", "left").select("src", "dst", "mult", F.least("src", "least").alias("label"))
    least = F.min("dst").over(Window.partitionBy("src"))
    return rows.select("src", "dst", "mult", F.least("src", least).alias("label"))


def _deliver(state: DataFrame) -> DataFrame:
    """Both rewrites in one projection. (v,u) with u other than l(v) becomes (u, l(v)), a propagation; (v,u) with u
    equal to l(v) turns into (u, v); label records travel to their own vertex."""
    is_edge = F.col("dst").isNotNull()
    moves = is_edge & (F.col("dst") != F.col("label"))
    return state.select(
        F.when(is_edge, F.col("dst")).otherwise(F.col("src")).alias("src"),
        F.when(is_edge, F.when(moves, F.col("label")).otherwise(F.col("src"))).alias("dst"),
        "mult",
        F.col("label").alias("sender"),
        F.when(moves, F.col("mult")).otherwise(0).alias("moved"),
        F.when(moves & (F.col("src") != F.col("label")), F.col("mult")).otherwise(0).alias("loud"),
    )


def _folded(state: DataFrame, by_source: bool) -> DataFrame:
    """Equal delivered rows as one with their number. Dealt ``by_source`` the fold and the window after it share one exchange."""
    rows = _deliver(state)
    return (rows.repartition("src") if by_source else rows).groupBy("src", "dst").agg(
        F.sum("mult").alias("mult"), F.min("sender").alias("low"), F.max("sender").alias("high"),
        F.sum("moved").alias("moved"), F.sum("loud").alias("loud"),
    )


def _step(layout: str, fanin: int, salts: int):
    """The step as a plan. Its rows carry the least and the greatest sender of the row (low, high) and of its source
    (label, top), the label before the step (before), and how many rows its source has (degree)."""
    before = F.when(F.col("dst").isNull(), F.col("low"))

    def compact(state: DataFrame) -> DataFrame:
        per = Window.partitionBy("src")
        return _folded(state, True).select(
            "src", "dst", "mult", F.min("low").over(per).alias("label"), "moved", "loud", "low", "high",
            F.max(before).over(per).alias("before"), F.max("high").over(per).alias("top"), F.count("*").over(per).alias("degree"),
        )

    def spread(state: DataFrame) -> DataFrame:
        """No task ever holds all edges of a vertex: minima are folded before the exchange, then joined back."""
        folded = materialize(_folded(state, False))
        level = folded.select("src", "low", "high", before.alias("before"), F.lit(1).cast("long").alias("n"), F.pmod(F.hash("dst"), F.lit(salts)).alias("salt"))
        fold = [F.min("low").alias("low"), F.max("high").alias("high"), F.max("before").alias("before"), F.sum("n").alias("n")]
        width = salts
        while fanin and width > 1:
            level = level.groupBy("src", "salt").agg(*fold).withColumn("salt", F.floor(F.col("salt") / fanin).cast("int"))
            width = -(-width // fanin)
        best = level.groupBy("src").agg(*fold).select("src", F.col("low").alias("label"), F.col("high").alias("top"), "before", F.col("n").alias("degree"))
        out = folded.join(best, "src").select("src", "dst", "mult", "label", "moved", "loud", "low", "high", "before", "top", "degree")
        out._starfold_source = folded
        return out

    return compact if layout == "compact" else spread


def _measures() -> list:
    vertex = F.col("dst").isNull()
    lowest = F.least(F.col("label"), F.col("before"))
    return [
        F.coalesce(F.sum("mult"), F.lit(0)).alias("edges_out"),
        F.count_if(~vertex).alias("edges_mid"),
        F.coalesce(F.sum("moved"), F.lit(0)).alias("propagated"),
        F.coalesce(F.sum(F.when(~vertex, F.col("mult") - F.col("moved"))), F.lit(0)).alias("turned"),
        F.coalesce(F.sum("loud"), F.lit(0)).alias("active"),
        F.count_if(vertex & (F.col("label") < F.col("before"))).alias("lowered"),
        F.count_if(vertex & ((lowest != F.col("before")) | (F.col("top") != F.col("before")))).alias("mismatched"),
        F.coalesce(F.max("degree"), F.lit(0)).alias("largest_key"),
    ]


def _retire(state: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(labels of classes that are done, state of the others).

    A class is done when no row of the step had a sender or a recipient of it that disagreed with the other end. A
    folded row has at most two senders, its least and its greatest, so both ends of every row are at hand.
    """
    off = (F.col("low") != F.col("before")) | (F.col("high") != F.col("before")) | (F.col("label") != F.col("before"))
    open_ = state.where(off).select(F.explode(F.array("low", "high", "before", "label")).alias("label")).distinct()
    done = _labels(state).join(open_.withColumnRenamed("label", "component"), "component", "left_anti").select("vertex", "component")
    return materialize(done), materialize(state.join(open_, "label", "left_semi"))


def _labels(state: DataFrame) -> DataFrame:
    return state.where("dst is null").select(F.col("src").alias("vertex"), F.col("label").alias("component"))


def add_isolated(labels: DataFrame, vertices: DataFrame | None) -> DataFrame:
    """Vertices that no edge names keep their own id."""
    if vertices is None:
        return labels
    lone = vertices.select("vertex").where("vertex is not null").distinct().join(labels.select("vertex"), "vertex", "left_anti")
    return labels.unionByName(lone.select("vertex", F.col("vertex").alias("component")))


@tidy
def run_twins(
    directed: DataFrame, *, stop: str = "edge_agreement", max_steps: int = 200, layout: str = "auto",
    fanin: int = 0, salts: int = 16, retire: bool = False, trace: bool = False, hub_rows: int = HUB_ROWS, cut: bool = True,
) -> ComponentResult:
    """Run on directed edges as they are given; see ``connected_components``. ``cut=False`` takes ``max_steps`` steps whatever the rule says."""
    if layout not in LAYOUTS:
        raise ValueError(f"layout is one of {LAYOUTS}")
    ended = rule(stop)
    spread = layout == "spread" or (layout == "auto" and _largest_source(directed) > hub_rows)
    state = materialize(_initial(directed, spread))
    finished: list[DataFrame] = []
    metrics: list[dict] = []
    history = [state] if trace else []
    converged = False
    size = None
    for k in range(1, max_steps + 1):
        began = time.monotonic()
        plan = _step("spread" if spread else "compact", fanin, salts)(state.select("src", "dst", "mult", "label"))
        nxt = materialize(plan, _measures())
        row = dict(nxt.measured) | {"step": k, "layout": "spread" if spread else "compact"}
        row["edges_in"] = size if size is not None else row["edges_out"]
        row["dups_within"] = row["edges_out"] - row["edges_mid"]
        row["dups_across"] = 0
        size = row["edges_out"]
        metrics.append(row)
        discard(*[getattr(plan, "_starfold_source", None)] * spread, *[] if trace else [state])
        state = nxt
        # Every component ends as a star, so hubs grow: from the first big one on no task holds a source whole.
        spread = spread or (layout == "auto" and row["largest_key"] > hub_rows)
        if trace:
            history.append(state)
        if ended(row):
            converged = True
            if cut:
                row["elapsed_ms"] = (time.monotonic() - began) * 1000
                break
        if retire:
            done, rest = _retire(state)
            finished.append(done)
            discard(*[] if trace else [state])
            state, size = rest, None
        row["elapsed_ms"] = (time.monotonic() - began) * 1000
    labels = _labels(state)
    for part in finished:
        labels = labels.unionByName(part)
    edges = state.where("dst is not null").select("src", "dst", "mult")
    return ComponentResult(labels, metrics, edges, converged, 1, history, [state, *finished])


def connected_components(
    edges: DataFrame, *, vertices: DataFrame | None = None, stop: str = "edge_agreement", max_steps: int = 200,
    layout: str = "auto", combine: str = "partial", fanin: int = 2, salts: int = 16, retire: bool = False,
    trace: bool = False, hub_rows: int = HUB_ROWS,
) -> ComponentResult:
    """Components of an undirected graph ``(a, b)`` by the alternating method.

    ``layout="compact"`` takes one exchange a step. ``layout="spread"`` keeps the edges of a hub in many tasks.
    ``layout="auto"`` is compact until a source has more than ``hub_rows`` rows, then spread.
    ``combine="tree"`` (implies spread) reduces minima in salted levels of ``fanin``, the exclusive-write form.
    ``retire`` takes classes out of later steps once no edge of theirs disagrees.
    Loops, repeated and null edges are dropped first; no edges give no rows but those of ``vertices``.
    """
    directed = twins(normalize_edges(edges))
    if combine == "tree":
        layout = "spread"
    out = run_twins(
        directed, stop=stop, max_steps=max_steps, layout=layout, fanin=fanin if combine == "tree" else 0,
        salts=salts, retire=retire, trace=trace, hub_rows=hub_rows,
    )
    out.labels = add_isolated(out.labels, vertices)
    return out


def trace(edges: DataFrame, k: int) -> DataFrame:
    """Labels and edges after each of exactly ``k`` steps: (step, src, dst, mult, label); dst is null on label rows."""
    out = run_twins(twins(normalize_edges(edges)), stop="quiet_counter", max_steps=k, trace=True, cut=False)
    parts = [h.select(F.lit(i).alias("step"), "src", "dst", "mult", "label") for i, h in enumerate(out.history)]
    whole = parts[0]
    for p in parts[1:]:
        whole = whole.unionByName(p)
    return whole
