"""Cost and accuracy measures: each a single aggregation over a log, an index or a prediction frame."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from pivotgrove.operators.index import IndexHandle
from pivotgrove.runtime import materialise


def timed(action: Callable) -> tuple[object, float]:
    """(result, seconds) of a callable that runs its Spark action itself."""
    began = time.perf_counter()
    out = action()
    return out, time.perf_counter() - began


def config_ratio(log: DataFrame, base: str, keys: tuple[str, ...] = ("dataset", "metric")) -> DataFrame:
    """log: (keys, config, value). Each configuration's value over the base configuration's."""
    zero = log.where(F.col("config") == base).select(*keys, F.col("value").alias("base_value"))
    return log.where(F.col("config") != base).join(zero, list(keys)).withColumn("ratio", F.col("value") / F.col("base_value"))


def index_bytes(ix: IndexHandle) -> DataFrame:
    """Bytes of the packed cells, of the points alone (8 a number and an id), and the share that the tree adds."""
    raw = F.sum("n_points") * (8 * ix.d + 8)
    return ix.cells.agg(F.sum(F.octet_length("packed")).alias("index_bytes"), raw.alias("point_bytes"), F.sum("n_points").alias("indexed_points")).withColumn("extra_share", F.col("index_bytes") / F.col("point_bytes") - 1)


def rebuild_fraction(log: DataFrame) -> DataFrame:
    """Points that rebuilds touched over the points of the sub-trees that a full rebuild would have touched."""
    return log.agg(F.sum("points_rebuilt").alias("rebuilt"), F.sum("points_full").alias("full"), (F.sum("points_rebuilt") / F.sum("points_full")).alias("fraction"), F.count("*").alias("rebuilds"))


def query_time(access: DataFrame) -> DataFrame:
    return access.groupBy("strategy").agg(F.avg("elapsed_us").alias("mean_us"), F.count("*").alias("queries"))


def points_accessed(access: DataFrame, detail: bool = False) -> DataFrame:
    more = [F.avg(c).alias(f"mean_{c}") for c in ("nodes_visited", "leaves_visited", "pruned_nodes")] if detail else []
    return access.groupBy("strategy").agg(F.avg("points_accessed").alias("mean_points_accessed"), *more)


def factor_ratio(access: DataFrame, value: str = "points_accessed") -> DataFrame:
    """Breadth over depth first, and boxes over balls: mean cost of each side over all queries."""
    side = lambda column, at: F.split_part(F.col(column), F.lit("_"), F.lit(at))
    mean = lambda test: F.avg(F.when(test, F.col(value)))
    order, volume = side("strategy", 2), side("strategy", 1)
    return access.agg((mean(order == "bfs") / mean(order == "dfs")).alias("bfs_over_dfs"), (mean(volume == "box") / mean(volume == "ball")).alias("box_over_ball"))


def mrr(ranked: DataFrame) -> DataFrame:
    """ranked: (qid, strategy, place, label). Mean of one over the place of the true best."""
    return ranked.where("strategy = label").agg(F.avg(1 / F.col("place")).alias("mrr"))


def macro_precision(predictions: DataFrame, never: str = "zero") -> DataFrame:
    """Mean over the classes seen as label of the share of right predictions; a class never predicted counts 0 or not."""
    classes = predictions.select(F.col("label").alias("c")).distinct()
    told = predictions.groupBy(F.col("prediction").alias("c")).agg(F.avg((F.col("prediction") == F.col("label")).cast("double")).alias("p"))
    each = classes.join(told, "c", "left")
    return each.agg(F.avg(F.coalesce("p", F.lit(0.0)) if never == "zero" else F.col("p")).alias("macro"))


def micro_precision(predictions: DataFrame) -> DataFrame:
    return predictions.agg(F.avg((F.col("prediction") == F.col("label")).cast("double")).alias("micro"))


def feature_gain(scores: DataFrame) -> DataFrame:
    """scores: (selector, features in f1|f, metric, value) -> both and their difference."""
    return scores.groupBy("selector", "metric").pivot("features", ["f1", "f"]).agg(F.first("value")).withColumn("gain", F.col("f") - F.col("f1"))


def selection_share(chosen: DataFrame) -> DataFrame:
    """The strategy chosen most, and its share of all queries."""
    each = chosen.groupBy("strategy").agg(F.count("*").alias("n"))
    total = F.sum("n").over(Window.partitionBy())
    return each.select("strategy", (F.col("n") / total).alias("share")).orderBy(F.desc("share"), "strategy").limit(1)


def prediction_share(predict_s: float, total_s: float) -> float:
    return predict_s / total_s if total_s else 0.0


def gain_over_mean(access: DataFrame, auto: DataFrame, value: str = "points_accessed") -> DataFrame:
    """One less the chosen strategies' cost over the mean cost of the four."""
    mean = access.agg((F.avg(value)).alias("mean_cost"))
    return auto.agg(F.avg(value).alias("auto_cost")).crossJoin(mean).withColumn("gain", 1 - F.col("auto_cost") / F.col("mean_cost"))


def mean_strategy_cost(access: DataFrame, value: str = "points_accessed") -> DataFrame:
    return access.groupBy("strategy").agg(F.avg(value).alias("cost")).agg(F.avg("cost").alias("mean_cost"))


def aepl(ix: IndexHandle, convention: str = "sequential") -> DataFrame:
    """Mean comparisons from a cell's root to a point's leaf, over all points, from the node frame's paths."""
    nodes = ix.nodes()
    width = nodes.where("parent_id >= 0").groupBy("cell_id", F.col("parent_id").alias("node_id")).agg(F.count("*").alias("t"))
    inner = nodes.join(width, ["cell_id", "node_id"]).select("cell_id", F.col("path").alias("parent_path"), "t", F.col("level").alias("depth"))
    leaves = nodes.where("is_leaf").select("cell_id", "node_id", "path", "n_points")
    steps = leaves.select("*", F.posexplode("path").alias("depth", "ordinal")).withColumn("parent_path", F.slice("path", F.lit(1), F.col("depth")))
    cost = F.least(F.col("ordinal") + 1, F.col("t") - 1) if convention == "sequential" else F.log2("t")
    each = steps.join(inner, ["cell_id", "parent_path", "depth"]).select((F.col("n_points") * cost).alias("c"))
    return each.agg(F.coalesce(F.sum("c"), F.lit(0)).alias("total")).crossJoin(nodes.where("is_leaf").agg(F.sum("n_points").alias("points"))).select((F.col("total") / F.col("points")).alias("aepl"))


def tree_shape(ix: IndexHandle) -> DataFrame:
    """Height, leaf fill and the worst child's share against an equal share."""
    nodes = ix.nodes()
    share = nodes.where("parent_id >= 0").groupBy("cell_id", "parent_id").agg((F.max("n_points") * F.count("*") / F.sum("n_points")).alias("worst"))
    return ix.stats().crossJoin(share.agg(F.max("worst").alias("worst_child"), F.avg("worst").alias("mean_worst_child")))


def speedup(log: DataFrame) -> DataFrame:
    """log: (dataset, slow, fast): mean and geometric mean of slow over fast."""
    x = F.col("slow") / F.col("fast")
    return log.agg(F.avg(x).alias("mean"), F.exp(F.avg(F.log(x))).alias("geometric_mean"))


def exactness(got: DataFrame, want: DataFrame) -> DataFrame:
    """Rows of either side that the other lacks, duplicates counted: (missing, extra), both 0 when equal. Each side is computed once."""
    got, want = materialise(got, "got"), materialise(want, "want")
    return want.exceptAll(got).agg(F.count("*").alias("missing")).crossJoin(got.exceptAll(want).agg(F.count("*").alias("extra")))


def pivot_rank_error(points: DataFrame, ix: IndexHandle, level: int = 0) -> DataFrame:
    """How far the cuts of one level are from the i/t quantiles of their node: greatest and mean."""
    nodes = ix.nodes().where((F.col("level") == level) & ~F.col("is_leaf"))
    cuts = nodes.select("cell_id", "path", "split_dim", F.size("pivots").alias("m"), F.posexplode("pivots").alias("i", "cut"))
    inside = ix.points().select("cell_id", "coords", F.slice("path", 1, level).alias("path"))
    each = inside.join(F.broadcast(cuts), ["cell_id", "path"]).groupBy("cell_id", "path", "i", "m").agg(F.avg((F.element_at("coords", F.col("split_dim") + 1) <= F.col("cut")).cast("double")).alias("f"))
    gap = F.abs(F.col("f") - (F.col("i") + 1) / (F.col("m") + 1))
    return each.agg(F.max(gap).alias("max_error"), F.avg(gap).alias("mean_error"))


def sse(points: DataFrame, centroids) -> float:
    from pivotgrove.operators.kmeans import step

    return step(points, centroids)[2]


def spark_io(spark, action: Callable) -> dict:
    """Shuffle, spill and task counts of what an action ran, from the status store of the session."""
    store = spark._jsparkSession.sparkContext().statusStore()
    jvm, none = spark._jvm, spark.sparkContext._gateway.new_array(spark._jvm.double, 0)
    stages = lambda: {(s.stageId(), s.attemptId()): s for s in _java_list(spark, store.stageList(None, False, False, none, jvm.java.util.ArrayList()))}
    before = set(stages())
    action()
    new = [s for k, s in stages().items() if k not in before]
    return {"stages": len(new), "tasks": sum(s.numTasks() for s in new), "shuffle_write": sum(s.shuffleWriteBytes() for s in new), "spill": sum(s.diskBytesSpilled() for s in new)}


def _java_list(spark, seq):
    return [seq.apply(i) for i in range(seq.size())]


