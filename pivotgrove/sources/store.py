"""Versioned index store: cells as Parquet by version, a manifest that names the current one."""

from __future__ import annotations

import base64
import json
import pickle
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pivotgrove.operators.index import CELL_SCHEMA, IndexHandle


def save(ix: IndexHandle, path: str, batches: list[int] | None = None) -> None:
    """Write the version's cells, then append its manifest row: a crash between the two leaves an unnamed folder.

    batches: the ids of stream batches that the version holds.
    """
    spark = ix.cells.sparkSession
    ix.cells.withColumn("stored", F.lit(ix.version)).repartitionByRange("cell_id").sortWithinPartitions("cell_id").write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("stored").parquet(f"{path}/cells")
    if ix.log is not None:
        ix.log.withColumn("stored", F.lit(ix.version)).write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("stored").parquet(f"{path}/log")
    head = {"params": ix.params.__dict__, "d": ix.d, "subs": {str(k): v for k, v in ix.subs.items()}, "logged": ix.log is not None and not ix.log.isEmpty(), "batches": batches or []}
    upper = base64.b64encode(pickle.dumps(ix.upper)).decode()
    spark.createDataFrame([(ix.version, json.dumps(head), upper)], "version long, head string, upper string").write.mode("append").parquet(f"{path}/manifest")


def versions(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.parquet(f"{path}/manifest").select("version").distinct()


def batches(spark: SparkSession, path: str) -> set[int]:
    """The ids of stream batches that the newest version holds."""
    return set(json.loads(spark.read.parquet(f"{path}/manifest").orderBy(F.desc("version")).first().head).get("batches", []))


def load(spark: SparkSession, path: str, version: int | None = None) -> IndexHandle:
    """The newest version, or a pinned one; the store is the engine's own, its manifest is trusted."""
    from pivotgrove.operators.insertion import LOG_SCHEMA
    from pivotgrove.operators.tree import Params

    rows = spark.read.parquet(f"{path}/manifest")
    rows = rows if version is None else rows.where(F.col("version") == version)
    found = rows.orderBy(F.desc("version")).first()
    if found is None:
        raise ValueError(f"no version {version} in {path}")
    head = json.loads(found.head)
    cells = spark.read.parquet(f"{path}/cells").where(F.col("stored") == found.version).drop("stored")
    empty = IndexHandle(spark.createDataFrame([], CELL_SCHEMA), pickle.loads(base64.b64decode(found.upper)), Params(**head["params"]), head["d"])
    log = spark.read.parquet(f"{path}/log").where(F.col("stored") == found.version).drop("stored") if head.get("logged") else None
    log = spark.createDataFrame(head["log"], LOG_SCHEMA) if head.get("log") else log  # as earlier manifests have it
    return replace(empty, cells=cells, version=found.version, subs={int(k): v for k, v in head["subs"].items()}, log=log)


def layout_by_cell(points: DataFrame) -> DataFrame:
    """Points in files of neighbouring cells, sorted by leaf: tight statistics for every coordinate column."""
    return points.repartitionByRange("cell_id").sortWithinPartitions("cell_id", "leaf_id")
