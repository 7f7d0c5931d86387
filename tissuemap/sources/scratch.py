"""Written intermediate tables: lineage cuts that survive lost executors."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def folder(spark: SparkSession) -> str:
    """The session's shared ``spark.checkpoint.dir``; a folder of this machine
    only where it is unset and Spark runs on this machine."""
    where = spark.conf.get("spark.checkpoint.dir", None)
    if not where:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a shared folder")
        where = tempfile.mkdtemp(prefix="tissuemap-")
        spark.conf.set("spark.checkpoint.dir", where)
    return where


def cut(df: DataFrame, label: str = "cut") -> DataFrame:
    path = f"{folder(df.sparkSession)}/{label}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)
