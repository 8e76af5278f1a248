"""Choosing a strategy for each query: query generation, labels, features, classifiers, dispatch."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.ml import Pipeline
from pyspark.ml.classification import DecisionTreeClassifier, LogisticRegression, MultilayerPerceptronClassifier, NaiveBayes, OneVsRest, RandomForestClassifier
from pyspark.ml.feature import MinMaxScaler
from pyspark.ml.functions import array_to_vector, vector_to_array
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from pivotgrove.operators.index import _SUB, IndexHandle
from pivotgrove.operators.search import at_cells, prepared, probes, visits
from pivotgrove.operators.tree import STRATEGIES
from pivotgrove.runtime import materialise, ship
from pivotgrove.sources.points import extent

MAX_PREFIXES = 256  #: leaves, or path prefixes where there are more, that a similarity feature compares with


# --- queries ---------------------------------------------------------------------------------------------------


def _drawn(points: DataFrame, m: int, seed: int) -> DataFrame:
    return points.select(F.xxhash64("pid", F.lit(seed)).alias("h"), "pid", "coords").orderBy("h", "pid").limit(m)


def gen_knn_queries(points: DataFrame, m: int, k_lo: int = 1, k_hi: int = 1000, seed: int = 0) -> DataFrame:
    """m data points as queries, k uniform in [k_lo, k_hi]."""
    k = F.lit(k_lo) + F.pmod(F.xxhash64("pid", F.lit(seed + 1)), F.lit(k_hi - k_lo + 1))
    return _drawn(points, m, seed).select(F.col("pid").alias("qid"), F.col("coords").alias("qcoords"), k.cast("long").alias("k"))


def gen_radius_queries(points: DataFrame, m: int, tau_lo: float = 0.001, tau_hi: float = 0.05, form: str = "diagonal", seed: int = 0) -> DataFrame:
    """m data points with r = tau times the extent: its diagonal, or the printed sum of squared sides."""
    d = len(points.select("coords").first()["coords"])
    side2 = F.aggregate(F.zip_with("hi", "lo", lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda s, x: s + x)
    ends = extent(points, d).select((F.sqrt(side2) if form == "diagonal" else side2).alias("reach"))
    tau = F.lit(tau_lo) + (tau_hi - tau_lo) * F.pmod(F.xxhash64("pid", F.lit(seed + 2)), F.lit(10_000)) / 10_000
    return _drawn(points, m, seed).crossJoin(F.broadcast(ends)).select(F.col("pid").alias("qid"), F.col("coords").alias("qcoords"), (tau * F.col("reach")).alias("r"))


def split_80_10_10(queries: DataFrame) -> tuple[DataFrame, DataFrame, DataFrame]:
    at = F.pmod(F.xxhash64("qid", F.lit(17)), F.lit(10))
    return queries.where(at < 8), queries.where(at == 8), queries.where(at == 9)


# --- labels ----------------------------------------------------------------------------------------------------


def label_queries(ix: IndexHandle, queries: DataFrame, operation: str = "knn", cost: str = "work", child_order: str = "nearest") -> DataFrame:
    """(qid, label, costs): the cheapest of the four strategies, all of them run.

    cost: "work" (nodes visited and points accessed, the same every time), "points" or "time".
    """
    return cheapest(strategy_costs(ix, queries, operation, child_order, timed=cost == "time"), cost)


def strategy_costs(ix: IndexHandle, queries: DataFrame, operation: str = "knn", child_order: str = "nearest", timed: bool = True) -> DataFrame:
    """(qid, strategy, work, points, time) of every query by each of the four strategies: one run for labels by any cost."""
    every = prepared(queries, "box_dfs").drop("strategy").withColumn("strategy", F.explode(F.array(*[F.lit(s) for s in STRATEGIES])))
    rows = visits(ix, every, operation == "knn", child_order, timed=timed, only="log")
    spent = {"work": F.col("nodes_visited") + F.col("points_accessed"), "points": F.col("points_accessed"), "time": F.col("elapsed_us")}
    return rows.groupBy("qid", "strategy").agg(*[F.sum(c).alias(name) for name, c in spent.items()])


def cheapest(costs: DataFrame, cost: str) -> DataFrame:
    """(qid, label, costs) of strategy_costs()."""
    each = costs.select("qid", "strategy", F.col(cost).alias("cost"))
    code = F.array_position(F.array(*[F.lit(s) for s in STRATEGIES]), F.col("strategy")).cast("int") - 1
    return each.groupBy("qid").agg(F.min_by(code, F.struct("cost", code)).alias("label"), F.map_from_entries(F.collect_list(F.struct("strategy", "cost"))).alias("costs"))


def label_early_stop(ix: IndexHandle, queries: DataFrame, operation: str = "knn") -> DataFrame:
    """(qid, label) by work, strategy after strategy: one is given up in a cell once it has cost more there than the best so far in all."""
    spark, is_knn = queries.sparkSession, operation == "knn"
    ship(spark)
    asked = materialise(prepared(queries, "box_dfs"), "queries")
    n, best = asked.count(), None
    for i, s in enumerate(STRATEGIES):
        some = probes(ix, asked.withColumn("strategy", F.lit(s)), is_knn)
        if best is not None:
            some = some.join(best.select("qid", F.col("cost").alias("budget")), "qid", "left")
        spent = at_cells(ix, some, n, is_knn, "nearest", False, only="log").groupBy("qid").agg(F.sum(F.col("nodes_visited") + F.col("points_accessed")).alias("cost"))
        if best is None:
            best = materialise(spent.withColumn("label", F.lit(0)), "labels")
        else:
            less = F.col("new") < F.col("cost")
            both = best.join(spent.withColumnRenamed("cost", "new"), "qid", "left")
            best = materialise(both.select("qid", F.when(less, F.col("new")).otherwise(F.col("cost")).alias("cost"), F.when(less, F.lit(i)).otherwise(F.col("label")).alias("label")), "labels")
    return best.select("qid", "label")


# --- features --------------------------------------------------------------------------------------------------


def path_similarity(a: Column, b: Column) -> Column:
    """Shared path nodes less differing ones less one for the root, over ordinals below the root; longer path counts."""
    longest = F.greatest(F.size(a), F.size(b))
    same = F.zip_with(a, b, lambda x, y: x.eqNullSafe(y))
    shared = F.aggregate(same, F.struct(F.lit(True).alias("on"), F.lit(0).alias("n")), lambda s, e: F.struct((s["on"] & e).alias("on"), (s["n"] + F.when(s["on"] & e, 1).otherwise(0)).alias("n")), lambda s: s["n"])
    return 2 * shared - longest


def similarity_graph(sample: DataFrame) -> DataFrame:
    """(src, dst, w) among a small sample of (pid, path): tests only, pairs grow with the square."""
    a, b = sample.select(F.col("pid").alias("src"), F.col("path").alias("pa")), sample.select(F.col("pid").alias("dst"), F.col("path").alias("pb"))
    return a.join(b, F.col("src") < F.col("dst")).select("src", "dst", path_similarity(F.col("pa"), F.col("pb")).alias("w"))


def upper_paths(ix: IndexHandle) -> list[tuple[int, ...]]:
    """The path of each leaf of the upper tier, in the leaves' order."""
    out: list[tuple[int, ...]] = []
    line: list[tuple] = [(ix.upper, ())]
    while line:
        node, path = line.pop()
        if node.idx is not None:
            out.append(path)
        else:
            line.extend((k, (*path, j)) for j, k in reversed(list(enumerate(node.kids))))
    return out


def leaf_paths(ix: IndexHandle, most: int = MAX_PREFIXES) -> tuple[list[tuple[int, ...]], int, int]:
    """(path prefixes, levels of the upper tier, levels inside a cell) of the deepest cut with `most` prefixes at most.

    Every cell belongs to a prefix: with more cells than that, prefixes end inside the upper tier.
    """
    above = upper_paths(ix)
    if len(above) > most:
        cut = max(c for c in range(max(map(len, above)) + 1) if len({p[:c] for p in above}) <= most)
        return sorted({p[:cut] for p in above}), cut, 0
    whole = max(map(len, above))
    nodes = ix.nodes().select(F.floor(F.col("cell_id") / _SUB).cast("int").alias("place"), "level", "is_leaf", "path")
    depth, best = 0, sorted(set(above))
    while True:
        keep = F.slice("path", 1, depth + 1)
        rows = nodes.where((F.size("path") == depth + 1) | (F.col("is_leaf") & (F.size("path") <= depth))).select("place", keep.alias("p")).distinct().limit(most + 1).collect()
        found = sorted({(*above[r.place], *r.p) for r in rows})
        if len(rows) > most or found == best:
            return best, whole, depth
        depth, best = depth + 1, found


def _similar(a: tuple[int, ...], b: tuple[int, ...]) -> int:
    same = 0
    while same < min(len(a), len(b)) and a[same] == b[same]:
        same += 1
    return 2 * same - max(len(a), len(b))


def features_f1(queries: DataFrame) -> DataFrame:
    """(qid, f1): the query's coordinates, and its k or r."""
    have = set(queries.columns)
    last = [F.col(c).cast("double") for c in ("k", "r") if c in have]
    return queries.select("qid", F.concat(F.col("qcoords").cast("array<double>"), F.array(*last)).alias("f1"))


def features_f2(ix: IndexHandle, queries: DataFrame, most: int = MAX_PREFIXES) -> DataFrame:
    """(qid, f2): similarity of the query's leaf to every leaf, or to path prefixes where the leaves are more.

    The query's leaf is the one that a point there would go to; similarities are looked up in a table of at most
    `most` squared numbers that goes to every task.
    """
    from pivotgrove.operators.insertion import route_to_leaf

    paths, above, depth = leaf_paths(ix, most)
    table = {p: [float(_similar(p, o)) for o in paths] for p in paths}
    shared = queries.sparkSession.sparkContext.broadcast((table, paths, [p[:above] for p in upper_paths(ix)], depth))

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known, every, upper, cut = shared.value
        for batch in batches:
            out = []
            for row in batch.to_pylist():
                p = (*upper[row["cell_id"] // _SUB], *row["path"][:cut])
                out.append(known.get(p) or [float(_similar(p, o)) for o in every])
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(out, pa.list_(pa.float64()))], ["qid", "f2"])

    leaf = route_to_leaf(queries.select(F.col("qid").alias("pid"), F.col("qcoords").alias("coords")), ix)
    return leaf.select(F.col("pid").alias("qid"), "cell_id", "path").mapInArrow(kernel, "qid long, f2 array<double>")


def features(ix: IndexHandle, queries: DataFrame, which: str = "f") -> DataFrame:
    """(qid, features): "f1", "f2", or both joined."""
    if which == "f1":
        return features_f1(queries).select("qid", array_to_vector("f1").alias("features"))
    if which == "f2":
        return features_f2(ix, queries).select("qid", array_to_vector("f2").alias("features"))
    both = features_f1(queries).join(features_f2(ix, queries), "qid")
    return both.select("qid", array_to_vector(F.concat("f1", "f2")).alias("features"))


# --- classifiers -----------------------------------------------------------------------------------------------


class Majority:
    """Always the commonest label."""

    def fit(self, df: DataFrame) -> Majority:
        self.share = {int(r.label): r["count"] for r in df.groupBy("label").count().collect()}
        return self

    def transform(self, df: DataFrame) -> DataFrame:
        total = sum(self.share.values())
        chance = [self.share.get(i, 0) / total for i in range(len(STRATEGIES))]
        return df.withColumn("probability", array_to_vector(F.array(*[F.lit(float(x)) for x in chance]))).withColumn("prediction", F.lit(float(int(np.argmax(chance)))))


def train_selector(rows: DataFrame, algo: str = "rf", seed: int = 0):
    """rows: (features, label). rf is the method; tree, ovr, mlp, bayes and majority stand in for other selectors."""
    rows = rows.withColumn("label", F.col("label").cast("double"))
    if algo == "majority":
        return Majority().fit(rows)
    width = len(rows.first()["features"])
    scaled = MinMaxScaler(inputCol="features", outputCol="scaled")
    made = {
        "rf": lambda: [RandomForestClassifier(seed=seed, numTrees=40, maxDepth=8)],
        "tree": lambda: [DecisionTreeClassifier(seed=seed, maxDepth=6)],
        "ovr": lambda: [scaled, OneVsRest(classifier=LogisticRegression(maxIter=30), featuresCol="scaled")],
        "mlp": lambda: [scaled, MultilayerPerceptronClassifier(layers=[width, 16, len(STRATEGIES)], seed=seed, maxIter=60, featuresCol="scaled")],
        "bayes": lambda: [scaled, NaiveBayes(featuresCol="scaled")],
    }[algo]()
    return Pipeline(stages=made).fit(rows)


def rank_strategies(model, rows: DataFrame) -> DataFrame:
    """(qid, strategy, place): strategies by falling probability; of a model without probabilities its choice first."""
    out = model.transform(rows)
    codes = F.array(*[F.lit(i) for i in range(len(STRATEGIES))])
    if "probability" in out.columns:
        chance = vector_to_array("probability")
    elif "rawPrediction" in out.columns:
        chance = vector_to_array("rawPrediction")
    else:
        chance = F.transform(codes, lambda i: F.when(i == F.col("prediction"), 1.0).otherwise(0.0))
    long = out.select("qid", F.posexplode(chance).alias("strategy", "p"))
    return long.select("qid", "strategy", F.row_number().over(Window.partitionBy("qid").orderBy(F.desc("p"), "strategy")).alias("place"))


def auto_search(ix: IndexHandle, queries: DataFrame, model, which: str = "f", operation: str = "knn") -> DataFrame:
    """Answers with the predicted strategy for each query: one search, the strategy a column."""
    from pivotgrove.operators.search import knn, radius

    chosen = predicted(ix, queries, model, which)
    return knn(ix, chosen) if operation == "knn" else radius(ix, chosen)


def predicted(ix: IndexHandle, queries: DataFrame, model, which: str = "f") -> DataFrame:
    told = model.transform(features(ix, queries, which)).select("qid", F.element_at(F.array(*[F.lit(s) for s in STRATEGIES]), F.col("prediction").cast("int") + 1).alias("strategy"))
    return materialise(queries.join(told, "qid"), "chosen")
