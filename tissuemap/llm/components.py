"""Connected components of a graph held as a distributed edge table.

Alternating star contractions: each round every node sends its neighbours to the
smallest node it knows. Rounds are written to the shared folder; the driver sees
two counters a round. Joins read written tables on both sides, so that Spark can
split the partition of a node with very many edges.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import discard, materialise


def _least(directed: DataFrame) -> DataFrame:
    return materialise(directed.groupBy("u").agg(F.min("v").alias("m")), "least")


def _signature(edges: DataFrame) -> tuple:
    row = edges.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
    return row[0], row[1]


def components(edges: DataFrame) -> DataFrame:
    """``node``, ``root`` for every node of ``edges`` (u long, v long).

    root is the smallest node of the component. No edges give no rows.
    """
    e = edges.filter("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct()
    e = materialise(e, "edges")
    before = None
    while (now := _signature(e)) != before:
        before = now
        # large star: neighbours above a node move to the least node around it
        both = e.unionByName(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        m = _least(both)
        big = both.join(m, "u").filter("v > u").select(F.col("v").alias("u"), F.least("m", "u").alias("v")).distinct()
        big = materialise(big, "large")
        # small star: a node and its lower neighbours move to the least of these
        m2 = _least(big)
        small = big.join(m2, "u").select(F.explode(F.array(F.struct(F.col("v").alias("u"), F.col("m").alias("v")), F.struct(F.col("u"), F.col("m").alias("v")))).alias("x")).select("x.*")
        small = small.filter("u <> v").distinct()
        new = materialise(small, "small")
        for old in (e, m, big, m2):
            discard(old)
        e = new
    roots = e.select(F.col("u").alias("node"), F.col("v").alias("root"))
    return materialise(roots.unionByName(e.select(F.col("v").alias("node"), F.col("v").alias("root"))).distinct(), "roots")
