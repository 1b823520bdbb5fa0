"""Incremental maintenance: new edges are contracted to current components, and only changed classes are rewritten."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from starfold.operators.alternating import connected_components
from starfold.sources.graphs import normalize_edges


def merge_edges(labels: DataFrame, new_edges: DataFrame) -> DataFrame:
    """Labels after insertion. Minima stay right, as the least of two minima is the least member of the union."""
    e = normalize_edges(new_edges)
    la = labels.select(F.col("vertex").alias("a"), F.col("component").alias("ca"))
    lb = labels.select(F.col("vertex").alias("b"), F.col("component").alias("cb"))
    moved = e.join(la, "a", "left").join(lb, "b", "left").select("a", "b", F.coalesce("ca", "a").alias("x"), F.coalesce("cb", "b").alias("y"))
    small = connected_components(moved.select(F.col("x").alias("a"), F.col("y").alias("b"))).whole()
    fresh = moved.select(F.explode(F.array(F.struct(F.col("a").alias("vertex"), F.col("x").alias("component")), F.struct(F.col("b").alias("vertex"), F.col("y").alias("component")))).alias("v")).select("v.*").distinct().join(labels.select("vertex"), "vertex", "left_anti")
    names = small.select(F.col("vertex").alias("component"), F.col("component").alias("to"))
    return labels.unionByName(fresh).join(names, "component", "left").select("vertex", F.coalesce("to", "component").alias("component"))
