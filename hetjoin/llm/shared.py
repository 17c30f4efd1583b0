"""Shared folder, written tables and text helpers for the corpus operators."""

from __future__ import annotations

import atexit
import ctypes
import tempfile
import uuid
import zipfile
from contextlib import contextmanager, suppress
from pathlib import Path

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

_made: list[tuple[SparkSession, str]] = []


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir``.

    Where the session names none, local mode uses a temporary folder of this process, remembered
    in the session; on a cluster that is an error, as executors would not see it.
    """
    named = spark.sparkContext.getConf().get("spark.checkpoint.dir", None) or spark.conf.get("hetjoin.shared.dir", None)
    if not named:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir is not set")
        named = "file://" + tempfile.mkdtemp(prefix="hetjoin-")
        spark.conf.set("hetjoin.shared.dir", named)
    return named.rstrip("/")


def new_path(spark: SparkSession, tag: str) -> str:
    path = f"{shared_dir(spark)}/{tag}-{uuid.uuid4().hex}"
    if not _made:
        atexit.register(_remove_made)
    _made.append((spark, path))
    return path


def _remove_made() -> None:
    for spark, path in _made:
        _remove(spark, path)


# While a table is written: the shuffle files of the step go when it ends.
_WRITING = {"spark.sql.classic.shuffleDependency.fileCleanup.enabled": "true"}
# Arrow batches that go to Python workers; a session that sets sizes of its own keeps them.
_BATCHES = {"spark.sql.execution.arrow.maxRecordsPerBatch": ("10000", "2048"), "spark.sql.execution.arrow.maxBytesPerBatch": ("67108864b", "4m")}


@contextmanager
def _settings(spark: SparkSession, wanted: dict[str, str]):
    before = {k: spark.conf.get(k, None) for k in wanted}
    for k, v in wanted.items():
        spark.conf.set(k, v)
    try:
        yield
    finally:
        for k, v in before.items():
            if v is None:
                spark.conf.unset(k)
            else:
                spark.conf.set(k, v)


def written(df: DataFrame, tag: str) -> DataFrame:
    """Cuts the lineage: writes ``df`` into the shared folder and reads it back."""
    spark = df.sparkSession
    path = new_path(spark, tag)
    with _settings(spark, _WRITING):
        df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._table_path = path
    return out


def discard(*tables: DataFrame | None) -> None:
    """Removes written tables that nothing reads any more."""
    for df in tables:
        if path := getattr(df, "_table_path", None):
            _remove(df.sparkSession, path)
            df._table_path = None


def _remove(spark: SparkSession, path: str) -> None:
    with suppress(Exception):
        where = spark._jvm.org.apache.hadoop.fs.Path(path)
        where.getFileSystem(spark._jsc.hadoopConfiguration()).delete(where, True)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")


def spread(df: DataFrame) -> DataFrame:
    """A table of few partitions, dealt over all cores before heavy work; larger ones as they are."""
    cores = df.sparkSession.sparkContext.defaultParallelism
    return df.repartition(cores) if df._jdf.queryExecution().toRdd().getNumPartitions() < cores else df


def small_batches(batches, rows: int = 1024, size: int = 1 << 20):
    """Cuts Arrow batches so that one step holds at most ``rows`` rows and about ``size`` bytes."""
    for batch in batches:
        step = max(1, min(rows, int(batch.num_rows * size / max(batch.nbytes, 1)))) if batch.num_rows else 1
        for at in range(0, batch.num_rows, step):
            yield batch.slice(at, step)


def to_batch(columns: dict[str, pa.Array]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays(list(columns.values()), names=list(columns))


def ship(spark: SparkSession) -> None:
    """Makes this package importable in Python workers: once per context, as a zip that Spark hands out. Bounds Arrow batches, too."""
    for key, (default, smaller) in _BATCHES.items():
        if spark.conf.get(key, default) == default:
            spark.conf.set(key, smaller)
    context = spark.sparkContext
    if getattr(context, "_hetjoin_shipped", False):
        return
    root = Path(__file__).resolve().parents[1]
    target = Path(tempfile.mkdtemp(prefix="hetjoin-zip-")) / "hetjoin_package.zip"
    with zipfile.ZipFile(target, "w") as z:
        for p in sorted(root.rglob("*.py")):
            z.write(p, p.relative_to(root.parent))
    context.addPyFile(str(target))
    context._hetjoin_shipped = True


def _give_back() -> None:
    """Hands freed memory back to the system: a worker lives on for other steps, whose needs would add up."""
    pa.default_memory_pool().release_unused()
    with suppress(OSError, AttributeError):
        ctypes.CDLL(None).malloc_trim(0)


def arrow_map(df: DataFrame, function, schema) -> DataFrame:
    """``mapInArrow`` with this package at hand in the workers."""
    ship(df.sparkSession)

    def run(batches):
        try:
            yield from function(batches)
        finally:
            _give_back()

    return df.mapInArrow(run, schema)
