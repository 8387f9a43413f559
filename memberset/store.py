"""Filters on disk: Parquet by shard, with the spec beside it."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from .build import W
from .geometry import FilterSpec


def save(lines: DataFrame, spec: FilterSpec, path: str) -> None:
    """Lines sorted within their shard, so that a lookup of one line reads one row group."""
    lines.repartition("shard").sortWithinPartitions("shard", "line").write.partitionBy("shard").parquet(f"{path}/lines")
    lines.sparkSession.createDataFrame([(spec.to_json(),)], "value string").coalesce(1).write.text(f"{path}/spec")


def load(spark: SparkSession, path: str) -> tuple[DataFrame, FilterSpec]:
    spec = FilterSpec.from_json(spark.read.text(f"{path}/spec").first()[0])
    return spark.read.parquet(f"{path}/lines").select("shard", "line", *W, "ones"), spec


def describe(lines: DataFrame, spec: FilterSpec) -> dict:
    from .measure import load_summary

    row = load_summary(lines, spec).first()
    return {"kind": spec.kind, "k": spec.k, "choices": spec.choices, "bytes": spec.bytes, "capacity": spec.capacity, **row.asDict()}
