"""The methods from SQL: views, functions, and reconstruction by name."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from .config import VARIANTS, EngineConfig
from .functions.udtf import register as register_functions
from .plans.setup import Setup
from .plans.slices import reduce_samples, run_slices
from .sources.phantom_source import register as register_source
from .sources.tables import read

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def install(spark: SparkSession, sf_dir: str) -> None:
    """Views of the given tables, SQL functions, table functions, the phantom source."""
    for name in TABLES:
        read(spark, sf_dir, name).createOrReplaceTempView(name)
    register_functions(spark)
    register_source(spark)
    for name, args, body in (
        ("cx_abs", "re DOUBLE, im DOUBLE", "sqrt(re * re + im * im)"),
        ("rel_err", "est DOUBLE, truth DOUBLE", "abs(est - truth) / truth"),
        ("month_index", "ts TIMESTAMP", "(year(ts) - 1995) * 12 + month(ts) - 1"),
    ):
        kind = "INT" if name == "month_index" else "DOUBLE"
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({args}) RETURNS {kind} RETURN {body}")


def reconstruct(samples: DataFrame, setup: Setup, name: str = "par_bt", view: str | None = None, **settings) -> DataFrame:
    """Maps of all slices in ``samples`` by a named configuration, as a view too."""
    if name not in VARIANTS and not name.startswith("base_"):
        raise ValueError(f"unknown method {name}")
    maps = run_slices(reduce_samples(samples, [setup]), [setup], [name], EngineConfig(**settings))
    if view:
        maps.createOrReplaceTempView(view)
    return maps


def write_maps(maps: DataFrame, path: str) -> None:
    """Maps as Parquet, one folder per slice so that readers prune."""
    maps.write.mode("append").partitionBy("slice_id").parquet(path)
