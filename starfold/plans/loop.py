"""Driver loop shared by every iterative method: one materialized state and one metric row per step."""

from __future__ import annotations

import contextlib
import functools
import uuid
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, Observation, SparkSession

from starfold.session import ensure_checkpoint_dir

STEP_SCHEMA = (
    "step int, edges_in long, edges_mid long, edges_out long, propagated long, turned long, active long, "
    "lowered long, mismatched long, dups_within long, dups_across long, largest_key long, elapsed_ms double"
)
STEP_COLUMNS = [c.split()[0] for c in STEP_SCHEMA.split(", ")]


@dataclass
class ComponentResult:
    """What a method returns. ``converged`` is False when ``max_steps`` cut the run short."""

    labels: DataFrame
    metrics: list[dict] = field(default_factory=list)
    edges: DataFrame | None = None
    converged: bool = True
    passes_per_step: int = 1
    history: list[DataFrame] = field(default_factory=list)
    #: Tables that ``labels``, ``edges`` and ``history`` are read from; a run deletes all others it wrote.
    keep: list[DataFrame] = field(default_factory=list)

    @property
    def n_steps(self) -> int:
        return len(self.metrics)

    def whole(self) -> DataFrame:
        """The labels; a cut run has none that are right and raises."""
        if not self.converged:
            raise RuntimeError(f"not converged after {self.n_steps} steps")
        return self.labels

    @property
    def passes(self) -> int:
        return self.n_steps * self.passes_per_step

    def steps(self, spark: SparkSession) -> DataFrame:
        rows = [tuple(m.get(c) for c in STEP_COLUMNS) for m in self.metrics]
        return spark.createDataFrame(rows, STEP_SCHEMA)


def materialize(
    df: DataFrame, measure: list[Column] | None = None, then: Callable[[DataFrame], DataFrame] = lambda d: d, by: str | None = None,
) -> DataFrame:
    """Cut the lineage with a table in the shared folder, which survives lost executors.

    A written table also gives the planner the true size: the estimate that a checkpoint carries over is the
    product of its joins' estimates and grows without bound through an iteration. ``measure`` is aggregated while
    the rows are written, so no second reading is needed; the row is the attribute ``measured``.
    ``then`` is applied to the measured rows before they are written. Rows lie in a folder for each value of ``by``.
    """
    spark = df.sparkSession
    path = f"{ensure_checkpoint_dir(spark).rstrip('/')}/starfold-{spark.sparkContext.applicationId}/{uuid.uuid4().hex}"
    watch = Observation() if measure else None
    df = then(df.observe(watch, *measure) if measure else df)
    df.write.parquet(path, partitionBy=by)
    out = spark.read.schema(df.schema).parquet(path)
    out._starfold_path = path
    for made in _RUNS:
        made.append(out)
    if watch:
        out.measured = watch.get
    return out


@contextlib.contextmanager
def setting(spark: SparkSession, name: str, value: str) -> Iterator[None]:
    """A setting of the session that holds inside alone."""
    before = spark.conf.get(name, None)
    spark.conf.set(name, value)
    try:
        yield
    finally:
        spark.conf.unset(name) if before is None else spark.conf.set(name, before)


def brief_shuffles(spark: SparkSession) -> contextlib.AbstractContextManager[None]:
    """Inside, what a query exchanged is deleted when it ends, not when the driver happens to collect its garbage."""
    return setting(spark, "spark.sql.classic.shuffleDependency.fileCleanup.enabled", "true")


def discard(*tables: DataFrame) -> None:
    """Delete the tables behind materialized frames that nothing reads any more."""
    for df in tables:
        path = getattr(df, "_starfold_path", None)
        if path:
            sc = df.sparkSession.sparkContext
            where = sc._jvm.org.apache.hadoop.fs.Path(path)
            where.getFileSystem(sc._jsc.hadoopConfiguration()).delete(where, True)
            df._starfold_path = None


_RUNS: list[list[DataFrame]] = []


def tidy(method):
    """A run deletes the tables it wrote, but for those its result names, also when it ends in an error."""

    @functools.wraps(method)
    def run(*args, **options):
        made: list[DataFrame] = []
        _RUNS.append(made)
        kept: list[DataFrame] = []
        try:
            out = method(*args, **options)
            kept = [*out.keep, *out.history]
            return out
        finally:
            _RUNS[:] = [x for x in _RUNS if x is not made]
            discard(*[t for t in made if not any(t is k for k in kept)])

    return run
