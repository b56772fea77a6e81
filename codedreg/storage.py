"""Materialisation in the folder that driver and executors share."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def ensure_checkpoint_dir(spark: SparkSession) -> str:
    """The folder the cluster names; only a local session without one gets its own."""
    sc = spark.sparkContext
    if not sc._jsc.sc().getCheckpointDir().isDefined():
        named = sc.getConf().get("spark.checkpoint.dir")
        if not named and not sc.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir names no shared folder")
        sc.setCheckpointDir(named or tempfile.mkdtemp(prefix="codedreg-checkpoint-"))
    return sc._jsc.sc().getCheckpointDir().get()


def cut(df: DataFrame) -> DataFrame:
    """Materialised rows in a fixed layout; what stands above is not run again."""
    ensure_checkpoint_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def laid_out(df: DataFrame, by: str) -> DataFrame:
    """Materialised in one folder for each value of a column, so that a filter on it reads only its own files."""
    path = f"{ensure_checkpoint_dir(df.sparkSession)}/laid-{uuid.uuid4().hex}"
    df.repartition(by).write.partitionBy(by).parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)
