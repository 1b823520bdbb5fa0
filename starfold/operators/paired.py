"""The key-grouped and the sort-and-scan form, with duplicate control between steps.

Labels travel with the edges here: each vertex that is not its own minimum writes both twins to its minimum
and hands the minimum to its other neighbours, while local minima stay silent.
"""

from __future__ import annotations

import time

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from starfold.operators.alternating import add_isolated
from starfold.plans.loop import ComponentResult, discard, materialize, tidy
from starfold.sources.graphs import normalize_edges, twins

MODES = ("none", "within_step", "two_level")
MARKED = "src bigint, dst bigint, is_old boolean"


def emit(edges: DataFrame, bag: bool = False) -> DataFrame:
    """Marked edges of one step: (src, dst, is_old). Only propagating edges are marked old. ``bag`` says that edges may repeat."""
    per = Window.partitionBy("src")
    least = edges.select("src", "dst", F.least("src", F.min("dst").over(per)).alias("m"))
    lead = F.row_number().over(per.orderBy("dst")) == 1 if bag else F.lit(True)
    rows = least.select("src", "dst", "m", lead.alias("lead")).where("m <> src")
    pair = lambda a, b, old: F.struct(F.col(a).alias("src"), F.col(b).alias("dst"), F.lit(old).alias("is_old"))
    out = (
        F.when((F.col("dst") == F.col("m")) & F.col("lead"), F.array(pair("src", "m", False), pair("m", "src", False)))
        .when(F.col("dst") != F.col("m"), F.array(pair("dst", "m", False), pair("src", "dst", True)))
        .otherwise(F.array().cast("array<struct<src:bigint,dst:bigint,is_old:boolean>>"))
    )
    return rows.select(F.explode(out).alias("e")).select("e.*")


def _columns(batch) -> list[np.ndarray]:
    return [c.to_numpy(zero_copy_only=False) for c in batch.columns]


def scan_sources(batches):
    """``emit`` over edges sorted by (src, dst) in one pass: all that is carried from row to row is the last source and its minimum."""
    last, least = None, 0
    for batch in batches:
        if not batch.num_rows:
            continue
        src, dst = _columns(batch)
        lead = np.concatenate(([src[0] != last], src[1:] != src[:-1]))
        group = np.cumsum(lead)
        minima = np.concatenate(([least], np.minimum(src[lead], dst[lead])))
        m = minima[group]
        last, least = src[-1], m[-1]
        joins = lead & (dst == m) & (m != src)
        moves = (dst != m) & (m != src)
        a = np.concatenate((src[joins], m[joins], dst[moves], src[moves]))
        b = np.concatenate((m[joins], src[joins], m[moves], dst[moves]))
        old = np.zeros(len(a), bool)
        old[len(a) - int(moves.sum()):] = True
        yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64()), pa.array(old)], ["src", "dst", "is_old"])


def scan_neighbours(batches):
    """First new row of each pair, of marked rows sorted by (src, dst, old first); ``met_old`` says that the pair was there before. Only the last row is carried."""
    held = (None, None, False)
    for batch in batches:
        if not batch.num_rows:
            continue
        src, dst, old = _columns(batch)
        same = np.concatenate(([held[:2] == (src[0], dst[0])], (src[1:] == src[:-1]) & (dst[1:] == dst[:-1])))
        after_old = same & np.concatenate(([held[2]], old[:-1]))
        held = (src[-1], dst[-1], bool(old[-1]))
        take = ~old & (~same | after_old)
        yield pa.RecordBatch.from_arrays([pa.array(src[take], pa.int64()), pa.array(dst[take], pa.int64()), pa.array(after_old[take])], ["src", "dst", "met_old"])


def suppress(new: DataFrame, old: DataFrame | None = None, mode: str = "two_level") -> DataFrame:
    """Duplicate control alone: ``none`` keeps the bag, ``within_step`` the set, ``two_level`` also drops what was there before."""
    if mode not in MODES:
        raise ValueError(f"mode is one of {MODES}")
    if mode == "none":
        return new.select("src", "dst")
    if mode == "within_step" or old is None:
        return new.select("src", "dst").distinct()
    return new.select("src", "dst").distinct().join(old.select("src", "dst"), ["src", "dst"], "left_anti")


def _grouped_step(state: DataFrame, mode: str) -> tuple[DataFrame, dict]:
    """One step by keys: marked edges are grouped by pair, and counted while they are written."""
    marked = emit(state, mode == "none")
    if mode == "none":
        rows = marked.select("src", "dst", F.when(F.col("is_old"), 0).otherwise(1).cast("long").alias("n_new"), F.col("is_old").cast("long").alias("n_old"))
        keep = F.col("n_new") > 0
    else:
        rows = marked.groupBy("src", "dst").agg(F.count_if(~F.col("is_old")).alias("n_new"), F.count_if("is_old").alias("n_old"))
        keep = (F.col("n_new") > 0) & (F.lit(mode == "within_step") | (F.col("n_old") == 0))
    counts = [
        F.count_if(keep).alias("edges_out"), F.count_if(F.col("n_new") > 0).alias("pairs"),
        F.coalesce(F.sum("n_new"), F.lit(0)).alias("fresh"), F.coalesce(F.sum("n_old"), F.lit(0)).alias("busy"),
    ]
    out = materialize(rows, counts, lambda d: d.where(keep).select("src", "dst"))
    return out, dict(out.measured)


def _sorted_step(state: DataFrame, mode: str) -> tuple[DataFrame, dict]:
    """One step by sorted passes: the first row of a source decides its role, and a pair's fate is seen from the row before."""
    counts = [F.count_if(~F.col("is_old")).alias("fresh"), F.count_if("is_old").alias("busy")]
    arranged = state.repartitionByRange("src").sortWithinPartitions("src", "dst").mapInArrow(scan_sources, MARKED)
    if mode == "none":
        out = materialize(arranged, counts, lambda d: d.where("not is_old").select("src", "dst"))
        return out, dict(out.measured) | {"edges_out": out.measured["fresh"], "pairs": out.measured["fresh"]}
    marked = materialize(arranged, counts)
    order = marked.repartitionByRange("src", "dst").sortWithinPartitions("src", "dst", F.col("is_old").desc())
    first = order.mapInArrow(scan_neighbours, "src bigint, dst bigint, met_old boolean")
    keep = F.lit(mode == "within_step") | ~F.col("met_old")
    out = materialize(first, [F.count("*").alias("pairs"), F.count_if(keep).alias("edges_out")], lambda d: d.where(keep).select("src", "dst"))
    row = dict(marked.measured) | dict(out.measured)
    discard(marked)
    return out, row


@tidy
def _run(directed: DataFrame, dedupe: str, how: str, max_steps: int, trace: bool) -> ComponentResult:
    if dedupe not in MODES:
        raise ValueError(f"dedupe is one of {MODES}")
    one = _sorted_step if how == "sort" else _grouped_step
    state = materialize(directed.distinct().select("src", "dst"), [F.count("*").alias("n")])
    everyone = materialize(state.select(F.col("src").alias("vertex")).distinct())
    edges = state.measured["n"]
    metrics, history, converged = [], [state] if trace else [], False
    while len(metrics) < max_steps:
        if edges == 0:
            converged = True
            break
        began = time.monotonic()
        nxt, row = one(state, dedupe)
        metrics.append({
            "step": len(metrics) + 1, "edges_in": edges, "edges_mid": row["fresh"] + row["busy"], "edges_out": row["edges_out"],
            "propagated": row["busy"], "turned": row["fresh"] - row["busy"], "active": row["busy"], "lowered": None, "mismatched": row["busy"],
            "dups_within": row["fresh"] - row["pairs"], "dups_across": row["pairs"] - row["edges_out"], "elapsed_ms": (time.monotonic() - began) * 1000,
            "carried_values": 5 if how == "sort" else None,
        })
        edges = row["edges_out"]
        if trace:
            history.append(nxt)
        else:
            discard(state)
        state = nxt
        if row["busy"] == 0:
            converged = True
            break
    final = state.groupBy("src").agg(F.min("dst").alias("m"))
    labels = final.select(F.col("src").alias("vertex"), F.least("src", "m").alias("component"))
    return ComponentResult(add_isolated(labels, everyone), metrics, state, converged, 2 if dedupe != "none" else 1, history, [state, everyone])


def connected_components(edges: DataFrame, *, vertices: DataFrame | None = None, dedupe: str = "two_level", max_steps: int = 200, trace: bool = False) -> ComponentResult:
    """The two-round key-grouped form; ``dedupe`` other than ``two_level`` gives the one-round forms."""
    out = _run(twins(normalize_edges(edges)), dedupe, "group", max_steps, trace)
    out.labels = add_isolated(out.labels, vertices)
    return out


def sorted_components(edges: DataFrame, *, vertices: DataFrame | None = None, dedupe: str = "two_level", max_steps: int = 200, trace: bool = False) -> ComponentResult:
    """The sort-and-scan form: sorted range partitions are scanned with a few carried values; memory does not grow with a source."""
    out = _run(twins(normalize_edges(edges)), dedupe, "sort", max_steps, trace)
    out.labels = add_isolated(out.labels, vertices)
    return out


def local_only(edges: DataFrame, max_steps: int = 12) -> list[int]:
    """Negative variant: single twins without a shared label. Counts changed minima per step; it need not settle."""
    state = materialize(twins(normalize_edges(edges)))
    seen: DataFrame | None = None
    changed = []
    for _ in range(max_steps):
        per = Window.partitionBy("src")
        rows = state.select("src", "dst", F.least("src", F.min("dst").over(per)).alias("m"))
        now = materialize(rows.select("src", "m").distinct())
        if seen is not None:
            both = now.join(seen.withColumnRenamed("m", "m0"), "src", "full")
            changed.append(both.where(~F.col("m").eqNullSafe(F.col("m0"))).count())
        seen = now
        state = materialize(rows.select(F.col("dst").alias("src"), F.when(F.col("dst") != F.col("m"), F.col("m")).otherwise(F.col("src")).alias("dst")))
    return changed
