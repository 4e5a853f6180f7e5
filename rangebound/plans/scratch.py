"""A folder that all executors share."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def scratch_dir(spark: SparkSession) -> str:
    """Under spark.checkpoint.dir; only where that is unset on one machine (tests) a local folder is taken."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not spark.sparkContext.master.startswith("local[") and spark.sparkContext.master != "local":
            raise RuntimeError("spark.checkpoint.dir names no folder that all executors share")
        base = tempfile.mkdtemp(prefix="rangebound-")
        spark.conf.set("spark.checkpoint.dir", base)
    return f"{base.rstrip('/')}/rangebound-{uuid.uuid4().hex}"


def materialise(df: DataFrame) -> DataFrame:
    """The rows as written to a folder that all executors share: lineage ends there, and a lost executor takes nothing."""
    spark = df.sparkSession
    path = scratch_dir(spark)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)
