"""What the operators share: tables in the shared folder, input columns and a text-to-words helper."""

from __future__ import annotations

import contextlib
import ctypes
import gc
import threading
import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from starfold.session import ensure_checkpoint_dir

#: Fixed byte table: A-Z to a-z; every ASCII byte but 0-9, A-Z and a-z to a space.
WORD_BYTES = bytes(
    (b + 32 if 65 <= b <= 90 else b) if b >= 128 or 48 <= b <= 57 or 65 <= b <= 90 or 97 <= b <= 122 else 32
    for b in range(256)
)


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def stored(df: DataFrame) -> DataFrame:
    """The rows as a table in the shared folder: a cut that survives lost executors and is computed once."""
    spark = df.sparkSession
    path = f"{ensure_checkpoint_dir(spark).rstrip('/')}/llm-{spark.sparkContext.applicationId}/{uuid.uuid4().hex}"
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._stored_path = path
    for made in _SCOPES:
        made.append(out)
    return out


def discard(*tables: DataFrame) -> None:
    """Delete stored tables that nothing reads any more."""
    for df in tables:
        path = getattr(df, "_stored_path", None)
        if path:
            sc = df.sparkSession.sparkContext
            folder = sc._jvm.org.apache.hadoop.fs.Path(path)
            folder.getFileSystem(sc._jsc.hadoopConfiguration()).delete(folder, True)
            df._stored_path = None


_SCOPES: list[list[DataFrame]] = []


@contextlib.contextmanager
def scratch() -> Iterator[list[DataFrame]]:
    """Every table stored inside is deleted at the end, also after an error, but for those taken out of the list."""
    made: list[DataFrame] = []
    _SCOPES.append(made)
    try:
        yield made
    finally:
        _SCOPES[:] = [x for x in _SCOPES if x is not made]
        discard(*made)


#: Seconds without a task after which a Python worker gives back what it holds between tasks.
REST_S = 2.0
_REST: dict = {"timer": None, "drops": {}}


def _let_go() -> None:
    for drop in list(_REST["drops"].values()):
        drop()
    gc.collect()
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):
        ctypes.CDLL(None).malloc_trim(0)


def _busy() -> None:
    if _REST["timer"]:
        _REST["timer"].cancel()


def _idle(drops: tuple[Callable[[], None], ...]) -> None:
    _busy()
    _REST["drops"] |= {(d.__module__, d.__qualname__): d for d in drops}
    _REST["timer"] = threading.Timer(REST_S, _let_go)
    _REST["timer"].daemon = True
    _REST["timer"].start()


def resting(step: Callable, *drops: Callable[[], None]) -> Callable:
    """``step`` of mapInArrow, after whose last task the worker calls ``drops`` and gives free memory back.

    Spark keeps an idle worker for a minute, beside the heap of the stages that follow. Tasks of a stage follow each
    other within ``REST_S``, so they share what the worker holds. The timer is held by this module, which workers
    import: what a function sent to them names itself is a copy.
    """

    def run(batches):
        _busy()
        try:
            yield from step(batches)
        finally:
            _idle(drops)

    return run


def crc_part(column: str, parts: int):
    """crc32 of an id as text, modulo ``parts``."""
    return F.crc32(F.col(column).cast("string").cast("binary")) % parts


def text_words(text: str | None) -> list[bytes]:
    """Lower-case ASCII words; every byte of other characters counts as part of a word."""
    return text.encode("utf-8", "surrogatepass").translate(WORD_BYTES).split() if text else []
