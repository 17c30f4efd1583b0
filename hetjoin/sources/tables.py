"""Readers and writers."""

from __future__ import annotations

import tempfile

from pyspark.sql import DataFrame, SparkSession


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")


def read(spark: SparkSession, fmt: str, path: str, schema: str | None = None, **options) -> DataFrame:
    """csv, json, orc or parquet; text formats need a schema, so that nothing is inferred from data."""
    if fmt in ("csv", "json") and schema is None:
        raise ValueError("text formats need a schema")
    reader = spark.read.format(fmt).options(**options)
    return (reader.schema(schema) if schema else reader).load(path)


def sink_placed(df: DataFrame, path: str, mode: str = "error") -> None:
    """Keeps a placement: one folder for each machine, pruned when a machine's part is read."""
    df.write.mode(mode).partitionBy("machine").parquet(path)


def sink_report(df: DataFrame, path: str, mode: str = "error") -> None:
    df.coalesce(1).write.mode(mode).json(path)


def stored(df: DataFrame) -> DataFrame:
    """A derived relation that is counted and then routed, computed once: checkpointed into ``spark.checkpoint.dir``.

    In local mode without such a folder, a temporary one is used.
    """
    context = df.sparkSession.sparkContext
    if context.getConf().get("spark.checkpoint.dir", None) is None and context.getCheckpointDir() is None:
        if not context.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir is not set")
        context.setCheckpointDir(tempfile.mkdtemp(prefix="hetjoin-"))
    return df.checkpoint()
