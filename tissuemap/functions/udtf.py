"""Table functions for SQL."""

from __future__ import annotations

import heapq

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf


class TopEntries:
    """rank and value of an array's largest entries."""

    def eval(self, values, k: int):
        for i, v in enumerate(heapq.nlargest(k, values or [])):
            yield i, float(v)


def register(spark: SparkSession) -> None:
    spark.udtf.register("top_entries", udtf(TopEntries, returnType="rank int, value double"))
