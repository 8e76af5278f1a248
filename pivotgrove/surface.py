"""What a user calls: searches that keep the payload, an estimator, SQL table functions over an index, cells as a table function."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf

from pivotgrove.operators import search, tree
from pivotgrove.operators.index import IndexHandle, build_index


def knn_with(queries: DataFrame, points: DataFrame, k: int, coords: list[str], key: str, point_key: str, strategy: str = "box_dfs", **options) -> DataFrame:
    """Every row of queries with its k nearest rows of points: all columns of queries, then rank, dist and those of points.

    coords are the numeric columns that both sides have; key and point_key identify their rows. Columns of points
    whose names queries has too are prefixed with near_.
    """
    at = lambda df, name, to: df.select(F.col(name).cast("long").alias(to), F.array(*[F.col(c).cast("double") for c in coords]).alias("coords" if to == "pid" else "qcoords"))
    found = search.knn(build_index(at(points, point_key, "pid"), **options), at(queries, key, "qid").withColumn("k", F.lit(k)), strategy)
    near = points.select(*[F.col(c).alias(f"near_{c}" if c in queries.columns else c) for c in points.columns])
    name = f"near_{point_key}" if point_key in queries.columns else point_key
    out = queries.join(found, queries[key].cast("long") == found["qid"]).join(near, F.col("pid") == F.col(name).cast("long"))
    return out.drop("qid", "pid")


@dataclass
class NearestNeighbours:
    """An estimator: fit(points) builds the index, the model's transform(queries) searches it."""

    k: int = 10
    strategy: str = "box_dfs"
    options: dict | None = None

    def fit(self, points: DataFrame) -> NearestNeighboursModel:
        return NearestNeighboursModel(self, build_index(points, **(self.options or {})))


@dataclass
class NearestNeighboursModel:
    estimator: NearestNeighbours
    index: IndexHandle

    def transform(self, queries: DataFrame) -> DataFrame:
        """(qid, neighbours): pids and distances in order, one row a query that has any."""
        asked = queries if "k" in queries.columns else queries.withColumn("k", F.lit(self.estimator.k))
        rows = search.knn(self.index, asked, self.estimator.strategy)
        ordered = F.array_sort(F.collect_list(F.struct("rank", "pid", "dist")))
        return rows.groupBy("qid").agg(F.transform(ordered, lambda x: F.struct(x["pid"].alias("pid"), x["dist"].alias("dist"))).alias("neighbours"))


def register_index(spark: SparkSession, ix: IndexHandle, name: str) -> None:
    """SQL table functions over an index: <name>_radius(q, r) and <name>_knn(q, k), each (pid, dist).

    Both read the view <name>_points; the radius function first tests the query's box, coordinate by coordinate.
    """
    at = [f"x{i}" for i in range(ix.d)]
    ix.points().select("pid", "cell_id", *[F.element_at("coords", i + 1).alias(x) for i, x in enumerate(at)]).createOrReplaceTempView(f"{name}_points")
    far = "sqrt(" + " + ".join(f"({x} - q[{i}]) * ({x} - q[{i}])" for i, x in enumerate(at)) + ")"
    box = " and ".join(f"{x} between q[{i}] - r and q[{i}] + r" for i, x in enumerate(at))
    spark.sql(f"create or replace temporary function {name}_radius(q array<double>, r double) returns table(pid bigint, dist double) return select pid, {far} from {name}_points where {box} and {far} <= r")
    spark.sql(f"create or replace temporary function {name}_knn(q array<double>, k int) returns table(pid bigint, dist double) return select pid, dist from (select pid, dist, row_number() over (order by dist, pid) as n from (select pid, {far} as dist from {name}_points)) where n <= k")


def register_cells(spark: SparkSession, ix: IndexHandle, name: str = "mwt_cell") -> None:
    """A table function of one row: the cell of a point, as (cell_id); for lateral joins over ad-hoc points."""
    from pivotgrove.operators.index import cell_ids
    from pivotgrove.runtime import ship

    ship(spark)
    router, subs = tree.Router.of(ix.upper), ix.subs

    @udtf(returnType="cell_id bigint")
    class Cell:
        def eval(self, pid: int, coords: list):
            import numpy as np

            yield (int(cell_ids(router, subs, np.array([coords], dtype=float), np.array([pid]))[0]),)

    spark.udtf.register(name, Cell)
