"""Raw readouts in binary files: one frame per slice, coil and time point.

A file holds frames one after the other. A frame is a header of five little-endian
32-bit integers (mark, slice, coil, time point, number of samples) and, per sample,
two 16-bit cell indices and two 32-bit floats (real, imaginary). Vendor formats
differ from scanner to scanner; they are brought to this layout first.

Defined results: an empty file has no frames; a file that ends within a frame or
lacks the mark where one is due is an error that names the file.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

MARK = 0x4B535031
SAMPLE = np.dtype([("ku", "<i2"), ("kv", "<i2"), ("re", "<f4"), ("im", "<f4")])
SHAPE = "slice_id long, coil int, t int, ku int, kv int, re float, im float"


def frame(slice_id: int, coil: int, t: int, ku, kv, re, im) -> bytes:
    """The bytes of one frame."""
    body = np.zeros(len(ku), SAMPLE)
    body["ku"], body["kv"], body["re"], body["im"] = ku, kv, re, im
    return np.array([MARK, slice_id, coil, t, len(body)], "<i4").tobytes() + body.tobytes()


def frames(content: bytes, name: str = "") -> Iterator[tuple[int, int, int, np.ndarray]]:
    """slice, coil, time point and samples of each frame."""
    at = 0
    while at < len(content):
        head = np.frombuffer(content, "<i4", min(5, (len(content) - at) // 4), at)
        end = at + 20 + (int(head[4]) * SAMPLE.itemsize if len(head) == 5 else 0)
        if len(head) < 5 or head[0] != MARK or head[4] < 0 or end > len(content):
            raise ValueError(f"broken frame at byte {at} of {name}")
        yield int(head[1]), int(head[2]), int(head[3]), np.frombuffer(content, SAMPLE, int(head[4]), at + 20)
        at = end


def _parse(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        for name, content in zip(b.column("path").to_pylist(), b.column("content").to_pylist(), strict=True):
            for slice_id, coil, t, x in frames(content or b"", name):
                n = len(x)
                keys = [pa.array(np.full(n, slice_id, np.int64)), pa.array(np.full(n, coil, np.int32)), pa.array(np.full(n, t, np.int32))]
                body = [pa.array(np.ascontiguousarray(x[c]).astype(k)) for c, k in (("ku", np.int32), ("kv", np.int32), ("re", np.float32), ("im", np.float32))]
                yield pa.record_batch([*keys, *body], [c.split()[0] for c in SHAPE.split(", ")])


def parse(files: DataFrame) -> DataFrame:
    """Samples of files given as (path, content)."""
    return files.select("path", "content").mapInArrow(_parse, SHAPE)


def read(spark: SparkSession, path: str, pattern: str = "*.raw") -> DataFrame:
    """Samples of all files below a folder, by Spark's reader of whole files."""
    return parse(spark.read.format("binaryFile").option("pathGlobFilter", pattern).option("recursiveFileLookup", "true").load(path))


def pack(samples: DataFrame) -> DataFrame:
    """(path, content): the samples (as in SHAPE) as one file per slice and coil."""

    def run(key, pdf):
        import pandas as pd

        parts = [frame(int(key[0]), int(key[1]), int(t), g["ku"], g["kv"], g["re"], g["im"]) for t, g in pdf.groupby("t", sort=True)]
        return pd.DataFrame({"path": [f"{key[0]}-{key[1]}.raw"], "content": [b"".join(parts)]})

    return samples.groupBy("slice_id", "coil").applyInPandas(run, "path string, content binary")


def event_samples(events: DataFrame) -> DataFrame:
    """``events`` as samples: slice by user, coil by kind of event, time point by hour,
    cell by ``k`` and the day."""
    kind = F.when(F.col("event_type") == "view", 0).when(F.col("event_type") == "click", 1).otherwise(2)
    k = F.get_json_object("props", "$.k").cast("int")
    return events.select(
        F.col("user_id").alias("slice_id"), kind.cast("int").alias("coil"), F.hour("ts").cast("int").alias("t"), k.alias("ku"), F.dayofmonth("ts").cast("int").alias("kv"),
        F.col("value").cast("float").alias("re"), (-F.col("value")).cast("float").alias("im"),
    )
