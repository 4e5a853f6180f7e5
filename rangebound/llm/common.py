"""Reading tables, the shared scratch folder, and held-out splits."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable, Iterable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def fold(key: str, modulus: int) -> Column:
    """crc32 of the id as text, modulo; null for a null id."""
    return F.crc32(F.col(key).cast("string")) % modulus


def scratch_dir(spark: SparkSession) -> str:
    """A new folder under spark.checkpoint.dir, which all executors share. Only where that is
    unset on one machine (tests) is a local folder taken; on a cluster it is an error."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not spark.sparkContext.master.startswith("local[") and spark.sparkContext.master != "local":
            raise RuntimeError("spark.checkpoint.dir names no folder that all executors share")
        base = tempfile.mkdtemp(prefix="rangebound-")
        spark.conf.set("spark.checkpoint.dir", base)
    return f"{base.rstrip('/')}/rangebound-{uuid.uuid4().hex}"


def free_of(df: DataFrame, names: Iterable[str]) -> DataFrame:
    """df without the columns that are named as a result's, in any case of letters; the result takes their place."""
    taken = {n.lower() for n in names}
    return df.select(*[c for c in df.columns if c.lower() not in taken])


def aside(df: DataFrame, names: Iterable[str]) -> tuple[DataFrame, Callable[[DataFrame], DataFrame]]:
    """df with such columns renamed, and what gives them their names back."""
    taken = {n.lower() for n in names}
    moved = {c: f"aside_{i}_{uuid.uuid4().hex[:8]}" for i, c in enumerate(df.columns) if c.lower() in taken}
    back = {v: k for k, v in moved.items()}
    return df.withColumnsRenamed(moved), lambda out: out.withColumnsRenamed(back)


def materialise(df: DataFrame) -> DataFrame:
    """Writes the rows as Parquet to the shared folder and reads them back: lineage ends there,
    and a lost executor takes nothing with it."""
    spark = df.sparkSession
    path = scratch_dir(spark)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def discard(df: DataFrame) -> None:
    """Deletes the files of a materialised frame that nothing reads any more."""
    spark = df.sparkSession
    for f in {x.rpartition("/")[0] for x in df.inputFiles()}:
        if "/rangebound-" in f:
            path = spark._jvm.org.apache.hadoop.fs.Path(f)
            path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def bounded_sample(df: DataFrame, key: Column, n: int) -> DataFrame:
    """n rows, by a hash of the key: those rows are thinned to about 2n where they are read, so that
    what tasks hand on doesn't grow with their number."""
    total = df.count()
    h = F.xxhash64(key)
    if total > 4 * n:
        df = df.where(F.pmod(h, F.lit(1 << 30)) < int((1 << 30) * (2 * n / total)))
    return df.orderBy(h, key).limit(n)
