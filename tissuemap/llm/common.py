"""Shared helpers: table access, scratch tables in shared storage, word rules."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: The six ASCII white-space characters that separate words.
BLANKS = " \t\n\x0b\x0c\r"
#: Java pattern for a run of them.
BLANK_RUN = r"[\x20\x09-\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables, read by Spark from any kind of path."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def scratch_dir(spark: SparkSession) -> str:
    """The folder that all executors share.

    It is the session's ``spark.checkpoint.dir``. Only where that is unset, as
    in local tests, a temporary folder of this machine is taken.
    """
    where = spark.conf.get("spark.checkpoint.dir", None)
    if not where:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a shared folder")
        where = tempfile.mkdtemp(prefix="llm-scratch-")
        spark.conf.set("spark.checkpoint.dir", where)
    return where


def materialise(df: DataFrame, label: str = "part") -> DataFrame:
    """Write ``df`` as Parquet into the shared folder and read it back.

    This cuts the lineage: a lost executor costs only its running tasks.
    """
    spark = df.sparkSession
    path = f"{scratch_dir(spark)}/{label}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    _made.append(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._scratch_path = path
    return out


#: Scratch tables written by this process and not deleted yet.
_made: list[str] = []


def _delete(spark: SparkSession, path: str) -> None:
    target = spark._jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark._jsparkSession.sessionState().newHadoopConf()).delete(target, True)
    if path in _made:
        _made.remove(path)


@contextmanager
def scratch(spark: SparkSession) -> Iterator[None]:
    """Delete on leaving what was materialised within: for a caller that has written
    its result by then."""
    before = set(_made)
    try:
        yield
    finally:
        for path in [p for p in _made if p not in before]:
            _delete(spark, path)


def discard(df: DataFrame) -> None:
    """Delete the files behind a frame made by :func:`materialise`."""
    path = getattr(df, "_scratch_path", None)
    if path:
        _delete(df.sparkSession, path)


def lower_ascii(col: Column) -> Column:
    """Lower-case A-Z only, whatever the locale or script."""
    return F.translate(col, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def words(text: Column) -> Column:
    """Words of a text as an array; none for null or blank texts."""
    body = F.trim(F.coalesce(text, F.lit("")), F.lit(BLANKS))
    return F.when(body == "", F.array().cast("array<string>")).otherwise(F.split(body, BLANK_RUN, -1))


def count_words(text: Column) -> Column:
    """Number of words: places where a word ends before a blank or the text's end."""
    return F.regexp_count(F.coalesce(text, F.lit("")), F.lit(r"[^\x20\x09-\x0D](?=[\x20\x09-\x0D]|\z)")).cast("long")


def text_bytes(column: pa.ChunkedArray | pa.Array) -> list[bytes]:
    """The UTF-8 bytes of a string column; null gives no bytes."""
    return [x or b"" for x in column.cast(pa.binary()).to_pylist()]


def run_starts(keys: np.ndarray) -> np.ndarray:
    """Positions where a new run of equal neighbours begins."""
    if not len(keys):
        return np.zeros(0, np.int64)
    return np.concatenate(([0], np.flatnonzero(keys[1:] != keys[:-1]) + 1))
