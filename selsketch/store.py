"""Intermediate tables in the folder that driver and executors share."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable, Iterable
from concurrent.futures import ThreadPoolExecutor

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """``spark.checkpoint.dir``, the context's checkpoint folder, or, on a single machine only, a temporary one."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.sparkContext.getCheckpointDir()
    if not found:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="shared-"))
        found = spark.sparkContext.getCheckpointDir()
    return found.rstrip("/")


def fresh(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"


def saved(df: DataFrame, name: str) -> DataFrame:
    """df written once and read back: what follows shares one run, and a lost executor costs no recomputation."""
    df.write.parquet(at := fresh(df.sparkSession, name))
    return df.sparkSession.read.schema(df.schema).parquet(at)


def each(spark: SparkSession, names: Iterable[str], make: Callable[[str], object], at_once: int = 4) -> dict:
    """name -> what is made of it, a few at a time: small jobs one by one leave cores idle."""
    shared_dir(spark)  # made once, before several ask for it
    names = list(names)
    with ThreadPoolExecutor(at_once) as pool:
        return dict(zip(names, pool.map(make, names), strict=True))


def dropped(*tables: DataFrame) -> None:
    """Deletes the files of saved tables."""
    for df in tables:
        spark = df.sparkSession
        for at in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
            path = spark._jvm.org.apache.hadoop.fs.Path(at)
            path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)
