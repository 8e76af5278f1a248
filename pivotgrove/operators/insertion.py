"""Insertion into the index: batches are dealt to cells, only the cells that they touch are rewritten."""

from __future__ import annotations

from dataclasses import replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from pivotgrove.operators import tree
from pivotgrove.operators.index import CELL_ARROW, CELL_SCHEMA, IndexHandle, _build_cell, as_matrix, cell_row, deal
from pivotgrove.runtime import materialise, ship
from pivotgrove.sources.points import validate

COMPACT_EVERY = 8  #: versions that a read meets at most before they are written as one
LOG_SCHEMA = "batch_id long, cell_id long, depth int, i0 int, i1 int, points_rebuilt long, points_full long, reason string"
_LOG_ARROW = pa.list_(pa.struct([("depth", pa.int32()), ("i0", pa.int32()), ("i1", pa.int32()), ("points_rebuilt", pa.int64()), ("points_full", pa.int64()), ("reason", pa.string())]))
_OUT = CELL_SCHEMA + ", log array<struct<depth:int,i0:int,i1:int,points_rebuilt:long,points_full:long,reason:string>>"


def route(batch: DataFrame, ix: IndexHandle) -> DataFrame:
    """(pid, coords, cell_id) of each point: the upper tier goes to the tasks, no exchange."""
    ship(batch.sparkSession)
    return deal(batch.select(F.col("pid").cast("long").alias("pid"), "coords"), ix.upper, ix.subs, ix.d)


def route_to_leaf(batch: DataFrame, ix: IndexHandle) -> DataFrame:
    """(pid, cell_id, path): the leaf that each point would go to."""
    ship(batch.sparkSession)
    d = ix.d

    def kernel(left: pa.Table, right: pa.Table) -> pa.Table:
        rows: dict[str, list] = {"pid": [], "cell_id": [], "path": []}
        if left.num_rows and right.num_rows:
            root, _, _ = tree.unpack(right["packed"][0].as_py())
            points = as_matrix(left["coords"], d)
            line = [(root, np.arange(len(points)), [])]
            while line:
                node, mine, path = line.pop()
                if node.idx is not None:
                    rows["pid"] += left["pid"].take(pa.array(mine)).to_pylist()
                    rows["cell_id"] += [right["cell_id"][0].as_py()] * len(mine)
                    rows["path"] += [path] * len(mine)
                    continue
                side = np.searchsorted(node.pivots, points[mine, node.dim], side="left")
                line.extend((node.kids[j], mine[side == j], [*path, j]) for j in np.unique(side).tolist())
        return pa.table({"pid": pa.array(rows["pid"], pa.int64()), "cell_id": pa.array(rows["cell_id"], pa.int64()), "path": pa.array(rows["path"], pa.list_(pa.int32()))})

    dealt = route(batch, ix).groupBy("cell_id")
    return dealt.cogroup(ix.cells.select("cell_id", "packed").groupBy("cell_id")).applyInArrow(kernel, "pid long, cell_id long, path array<int>")


def _merge(ix: IndexHandle, rebuild: str, version: int):
    d, params = ix.d, ix.params
    fresh_cell = _build_cell(params, d, version)

    def kernel(left: pa.Table, right: pa.Table) -> pa.Table:
        log: list[dict] = []
        if not right.num_rows:
            out = fresh_cell(left)
        else:
            root, points, pids = tree.unpack(right["packed"][0].as_py())
            new, ids = as_matrix(left["coords"], d), left["pid"].to_numpy()
            order = np.argsort(ids, kind="stable")
            points, pids = np.vstack((points, new[order])), np.concatenate((pids, ids[order]))
            log = tree.insert(root, points, pids, np.arange(len(pids) - len(ids), len(pids)), params, rebuild)
            out = pa.Table.from_pylist([cell_row(right["cell_id"][0].as_py(), root, points, pids, version)], schema=CELL_ARROW)
        return out.append_column("log", pa.array([log], _LOG_ARROW))

    return kernel


def insert_batch(ix: IndexHandle, batch: DataFrame, rebuild: str = "selective", bulk: bool = True) -> IndexHandle:
    """The next version, with the batch's points in. Cells that no point falls in keep their rows.

    rebuild: "selective", "full" or "none". bulk=False inserts point by point (a baseline for small batches).
    """
    ship(batch.sparkSession)
    good = validate(batch)[0].select("pid", "coords")
    if not bulk:
        for row in good.orderBy("pid").collect():  # a baseline on small batches: one job a point
            ix = insert_batch(ix, batch.sparkSession.createDataFrame([row], good.schema), rebuild)
        return ix
    version = ix.version + 1
    dealt = materialise(route(good, ix), "batch")
    touched = dealt.select("cell_id").distinct()
    old = ix.cells.join(F.broadcast(touched) if touched.count() <= 100_000 else touched, "cell_id", "left_semi")
    merged = materialise(dealt.groupBy("cell_id").cogroup(old.groupBy("cell_id")).applyInArrow(_merge(ix, rebuild, version), _OUT), "cells-merged")
    cells = ix.cells.join(merged.select("cell_id"), "cell_id", "left_anti").unionByName(merged.drop("log"))
    log = merged.select("cell_id", F.explode("log").alias("l")).select(F.lit(version).cast("long").alias("batch_id"), "cell_id", "l.*")
    out = replace(ix, cells=cells, version=version, log=log if ix.log is None else ix.log.unionByName(log))
    return compact(out) if version % COMPACT_EVERY == 0 else out


def compact(ix: IndexHandle) -> IndexHandle:
    """Write the cells of all versions into one table, and the log into another, so that reads no longer meet the chain of versions."""
    return replace(ix, cells=materialise(ix.cells, "index-cells"), log=None if ix.log is None else materialise(ix.log, "index-log"))


def rebuild_log(ix: IndexHandle, spark) -> DataFrame:
    return spark.createDataFrame([], LOG_SCHEMA) if ix.log is None else ix.log


# --- the balance criterion as DataFrame operations -----------------------------------------------------------


def audit_balance(nodes: DataFrame, omega: float) -> DataFrame:
    """Children that are too large for their parent: (cell_id, parent_id, ordinal, n_points, parent_points, t, omega)."""
    kids = nodes.where("parent_id >= 0").select("cell_id", "parent_id", "ordinal", "n_points")
    parents = kids.groupBy("cell_id", "parent_id").agg(F.sum("n_points").alias("parent_points"), F.count("*").alias("t"))
    least = (F.col("t") - 1) / F.col("t")
    used = F.when(F.lit(omega) > least, F.lit(omega)).otherwise(least + (1 - least) / 2)
    out = kids.join(parents, ["cell_id", "parent_id"]).withColumn("omega", used)
    return out.where((F.col("t") > 1) & (F.col("n_points") >= F.col("omega") / (F.col("t") - 1) * F.col("parent_points")))


def choose_rebuild_range(kids: DataFrame, omega: float, keys: tuple[str, ...] = ("cell_id", "parent_id"), span: str = "count") -> DataFrame:
    """(keys, violator, i0, i1, zeta): of every parent with a violation the contiguous siblings of fewest points.

    kids: (keys, ordinal, n_points). Running sums give every range of at most t siblings; the least is taken.
    """
    by = Window.partitionBy(*keys)
    base = kids.select(*keys, "ordinal", "n_points", F.sum("n_points").over(by).alias("total"), F.count("*").over(by).alias("t"), F.sum("n_points").over(by.orderBy("ordinal").rowsBetween(Window.unboundedPreceding, 0)).alias("upto"))
    bad = base.where(F.col("n_points") >= omega / (F.col("t") - 1) * F.col("total")).groupBy(*keys).agg(F.max_by("ordinal", F.struct("n_points", -F.col("ordinal"))).alias("violator"))
    a = base.select(*keys, F.col("ordinal").alias("i0"), (F.col("upto") - F.col("n_points")).alias("before"), "total", "t")
    b = base.select(*keys, F.col("ordinal").alias("i1"), "upto")
    ranges = a.join(b, list(keys)).join(bad, list(keys)).where("i0 <= violator and violator <= i1").withColumn("zeta", F.col("upto") - F.col("before"))
    many = F.col("i1") - F.col("i0") + (1 if span == "count" else 0)
    good = ranges.where(F.col("zeta") < many * omega / (F.col("t") - 1) * F.col("total"))
    best = good.groupBy(*keys, "violator").agg(F.min(F.struct("zeta", (F.col("i1") - F.col("i0")).alias("width"), "i0", "i1")).alias("b"))
    return best.select(*keys, "violator", "b.i0", "b.i1", "b.zeta")


