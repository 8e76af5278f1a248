"""The experiments on the given tables: W1 to W21, each (workload, dataset, config, metric, value) in long form.

Every experiment builds, searches and inserts through Spark, over all rows of its views. Query times are those
that the traversals themselves took, added up over the queries; build and insertion times are those of the jobs.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pivotgrove import metrics as M
from pivotgrove.baselines import trees as B
from pivotgrove.operators import insertion, kmeans, search, selector, tree
from pivotgrove.operators.index import IndexHandle, build_index
from pivotgrove.operators.tree import STRATEGIES
from pivotgrove.plans import cdf, fanout
from pivotgrove.runtime import shared_dir
from pivotgrove.sources.points import points, table
from pivotgrove.streaming import ingest

EIGHT = ("ord2", "evt2", "li2", "part2", "emb3", "li3", "evt3", "li4")
FIVE = ("ord2", "evt3", "li2", "li3", "li4")
DELTAS = (5e-4, 1e-3, 5e-3, 1e-2, 5e-2, 1e-1, 5e-1)
SUBS = (10, 50, 100, 500, 1000, 5000, 10000)
_SCHEMA = "workload string, dataset string, config string, metric string, value double"


def _frame(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    return spark.createDataFrame([(*map(str, r[:4]), float(r[4])) for r in rows], _SCHEMA)


def _view(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    data = points(spark, sf_dir, name).select("pid", "coords").cache()
    data.count()
    return data


def _build(data: DataFrame, **options) -> tuple[IndexHandle, float]:
    return M.timed(lambda: build_index(data, **options))


def _cost(ix: IndexHandle, asked: DataFrame, operation: str = "knn", strategy: str = "box_dfs") -> tuple[float, float]:
    """(seconds that all traversals took, points accessed a query)."""
    r = search.access_log(ix, asked, operation, strategy, "pivot").agg((F.sum("elapsed_us") / 1e6).alias("s"), F.avg("points_accessed").alias("n")).first()
    return float(r.s or 0), float(r.n or 0)


def _each(asked: DataFrame) -> DataFrame:
    return search.prepared(asked, "box_dfs").drop("strategy").withColumn("strategy", F.explode(F.array(*[F.lit(s) for s in STRATEGIES])))


def W1(spark: SparkSession, sf_dir: str, m: int = 100) -> DataFrame:
    """Balanced against equal-width cuts: build and kNN."""
    rows = []
    for view in ("li2", "evt2"):
        data = _view(spark, sf_dir, view)
        asked = selector.gen_knn_queries(data, m)
        for mode in ("sort", "equal_width"):
            ix, took = _build(data, mode=mode)
            s, n = _cost(ix, asked)
            rows += [("W1", view, mode, "build_s", took), ("W1", view, mode, "knn_s", s), ("W1", view, mode, "points_accessed", n)]
    return _frame(spark, rows)


def W2(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Depth against breadth first at a dense and at a remote point."""
    data = _view(spark, sf_dir, "evt2")
    value = F.element_at("coords", 1)
    ends = [data.where(value < 10).orderBy("pid").limit(1), data.orderBy(F.desc(value), "pid").limit(1)]
    asked = ends[0].withColumn("qid", F.lit(0).cast("long")).union(ends[1].withColumn("qid", F.lit(1).cast("long")))
    log = search.access_log(build_index(data), _each(asked.select("qid", F.col("coords").alias("qcoords"), F.lit(10).alias("k"))))
    got = log.select("qid", "strategy", (F.col("nodes_visited") + F.col("points_accessed")).alias("work")).collect()
    return _frame(spark, [("W2", ("dense", "tail")[r.qid], r.strategy, "work", r.work) for r in got])


def W3(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Eight points, capacity 3, fan-out 2 to 4: mean path length of the tree and of each objective."""
    data, rows = points(spark, sf_dir, "evt2").where("pid < 8"), []
    for t in (2, 3, 4):
        rows.append(("W3", "evt2", f"t={t}", "aepl", M.aepl(build_index(data, c=3, t=t, mode="sort")).first().aepl))
        rows += [("W3", "evt2", f"t={t}", name, f(8, 3, t)) for name, f in fanout.OBJECTIVES.items() if name != "printed"]
    return _frame(spark, rows)


def W4(spark: SparkSession, sf_dir: str, m: int = 100) -> DataFrame:
    """Fan-out sweep, c=30: objective, measured path length, 100 kNN."""
    data, rows = _view(spark, sf_dir, "li2"), []
    asked = selector.gen_knn_queries(data, m)
    for t in range(2, 11):
        ix, _ = _build(data, t=t, mode="sort")
        s, seen = _cost(ix, asked)
        rows += [("W4", "li2", f"t={t}", "aepl", M.aepl(ix).first().aepl), ("W4", "li2", f"t={t}", "knn_s", s), ("W4", "li2", f"t={t}", "points_accessed", seen), ("W4", "n=1e6", f"t={t}", "objective", fanout.aepl_printed(10**6, 30, t))]
    return _frame(spark, rows)


def W5(spark: SparkSession, sf_dir: str, m: int = 100) -> DataFrame:
    """Build, kNN and radius time against delta and l, as ratios of the base (delta 1e-4, l 5) over each."""
    rows = []
    for view in ("ord2", "li2"):
        data = _view(spark, sf_dir, view)
        near, within = selector.gen_knn_queries(data, m), selector.gen_radius_queries(data, m)

        def cell(delta: float, l: int) -> tuple[float, float, float]:  # noqa: E741
            ix, took = _build(data, delta=delta, l=l, t=8, mode="rank_corrected", small=0)
            return took, _cost(ix, near)[0], _cost(ix, within, "radius")[0]

        base = cell(1e-4, 5)
        for config, got in [(f"delta={d}", cell(d, 100)) for d in DELTAS] + [(f"l={n}", cell(0.01, n)) for n in SUBS]:
            rows += [("W5", view, config, f"{name}_ratio", b / g) for name, b, g in zip(("build", "knn", "radius"), base, got, strict=True)]
    return _frame(spark, rows)


def W6(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Width of the candidate window: rank error of the root's cuts, and the share of points that the windows hold."""
    data, rows, t, parts = _view(spark, sf_dir, "li2"), [], 4, 100
    values = data.select("pid", F.element_at("coords", 1).alias("x"), F.lit(0).alias("g"))
    ecdf = cdf.empirical_cdf(cdf.cdf_sample(values, 0.01, keys=["g"], least=64), ["g"], "x")
    roots = cdf.fit_root(ecdf, ["g"], "x", parts)
    told = cdf.predict_cdf(values, roots, cdf.fill_subs(cdf.fit_sub_plf(ecdf, roots, ["g"], "x", parts), ["g"], parts), ["g"], "x", parts)
    gap = F.least(*[F.abs(F.col("predicted") - i / t) for i in range(1, t)])
    kappas = (0.0, 0.01, 0.05, 0.1, 0.15, 1 / t)
    share = told.agg(*[F.avg((gap <= k).cast("double")).alias(f"k{i}") for i, k in enumerate(kappas)]).first()
    for i, kappa in enumerate(kappas):
        for mode in ("candidate_median", "rank_corrected"):
            ix, _ = _build(data, t=t, mode=mode, kappa=kappa, cell_points=1 << 30)
            rows.append(("W6", "li2", f"kappa={kappa:.2f}", f"rank_error_{mode}", M.pivot_rank_error(data, ix).first().max_error))
        rows.append(("W6", "li2", f"kappa={kappa:.2f}", "window_share", share[i]))
    return _frame(spark, rows)


def _builders() -> dict:
    return {"fast": lambda d: build_index(d, mode="inverse"), "base": lambda d: build_index(d, mode="sort"), "binary_kd": B.binary_kd, "ball": B.ball_tree, "rtree": B.packed_rtree, "forest": lambda d: B.forest(d.where("pid % 2 = 0")).insert(d.where("pid % 2 != 0"))}


def W7(spark: SparkSession, sf_dir: str, views: tuple[str, ...] = FIVE) -> DataFrame:
    """Build time of six builders as the number of points grows."""
    rows = []
    for view in views:
        data = _view(spark, sf_dir, view)
        for share in (0.2, 0.4, 0.6, 0.8, 1.0):
            some = data.where(F.pmod(F.xxhash64("pid", F.lit(23)), F.lit(10)) < int(10 * share)).cache()
            some.count()
            rows += [("W7", view, f"{name}@{share}", "build_s", M.timed(lambda f=f: f(some))[1]) for name, f in _builders().items()]
            some.unpersist()
        data.unpersist()
    return _frame(spark, rows)


def W8(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bytes of the packed index by builder on five views."""
    rows = []
    for view in FIVE:
        data = _view(spark, sf_dir, view)
        for name in ("fast", "base", "binary_kd", "ball", "rtree"):
            r = M.index_bytes(_builders()[name](data)).first()
            rows += [("W8", view, name, "bytes_per_point", r.index_bytes / r.indexed_points), ("W8", view, name, "extra_share", r.extra_share)]
    return _frame(spark, rows)


def W9(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A small device's build: all points in one task, by one core."""
    data, rows = _view(spark, sf_dir, "evt2").coalesce(1), []
    for mode in ("inverse", "rank_corrected", "sort"):
        ix, took = _build(data, mode=mode, cell_points=1 << 30)
        rows += [("W9", "evt2", mode, "build_s", took), ("W9", "evt2", mode, "bytes", M.index_bytes(ix).first().index_bytes)]
    return _frame(spark, rows)


def W10(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Insertion time against delta and l: a fifth of the points goes into an index of the others."""
    rows = []
    for view in ("ord2", "evt2", "li2"):
        data = _view(spark, sf_dir, view)
        fifth = F.pmod(F.xxhash64("pid", F.lit(29)), F.lit(5)) == 0
        for config, options in [(f"delta={d}", {"delta": d}) for d in DELTAS] + [(f"l={v}", {"l": v}) for v in SUBS]:
            ix, _ = _build(data.where(~fifth), t=4, small=0, **options)
            rows.append(("W10", view, config, "insert_s", M.timed(lambda ix=ix: insertion.insert_batch(ix, data.where(fifth)))[1]))
    return _frame(spark, rows)


def W11(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Insertion time against the number inserted: selective and whole rebuilds, none, the forest, a binary tree from scratch."""
    data, rows = _view(spark, sf_dir, "evt2"), []
    n = int(0.8 * (data.agg(F.max("pid")).first()[0] + 1))
    base = data.where(F.col("pid") < n)
    ix, forest = build_index(base, t=4), B.forest(base)
    for part in (1000, 100, 10, 5):
        batch = data.where((F.col("pid") >= n) & (F.col("pid") < n + max(1, n // part)))
        for how in ("selective", "full", "none"):
            new, took = M.timed(lambda how=how, batch=batch: insertion.insert_batch(ix, batch, how))
            cost = M.rebuild_fraction(insertion.rebuild_log(new, spark)).first()
            rows += [("W11", "evt2", f"{how}@n/{part}", "insert_s", took), ("W11", "evt2", f"{how}@n/{part}", "points_rebuilt", cost.rebuilt or 0)]
        rows.append(("W11", "evt2", f"forest@n/{part}", "insert_s", M.timed(lambda batch=batch: forest.insert(batch))[1]))
        rows.append(("W11", "evt2", f"scratch@n/{part}", "insert_s", M.timed(lambda batch=batch: B.binary_kd(base.unionByName(batch)))[1]))
    return _frame(spark, rows)


def W12(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Eighteen points under three children: which siblings are rebuilt."""
    i0, i1 = tree.rebuild_range([6, 3, 9], 0.8)
    return _frame(spark, [("W12", "fixture", "6,3,9", "points_rebuilt", sum([6, 3, 9][i0 : i1 + 1])), ("W12", "fixture", "6,3,9", "points_full", 18)])


def W13(spark: SparkSession, sf_dir: str, m: int = 100) -> DataFrame:
    """Breadth over depth first and boxes over balls, by points accessed and by time, on eight views."""
    rows = []
    for view in EIGHT:
        data = _view(spark, sf_dir, view)
        log = search.access_log(build_index(data), _each(selector.gen_knn_queries(data, m)), child_order="pivot").cache()
        for metric, column in (("time", "elapsed_us"), ("points", "points_accessed")):
            r = M.factor_ratio(log, column).first()
            rows += [("W13", view, "all", f"bfs_over_dfs_{metric}", r.bfs_over_dfs), ("W13", view, "all", f"box_over_ball_{metric}", r.box_over_ball)]
    return _frame(spark, rows)


def ground_truth(data: DataFrame, m: int, operation: str = "knn", cost: str = "time") -> tuple[IndexHandle, DataFrame, DataFrame]:
    """(index, queries, labels): k from 1 to 1000, the fastest strategy by the time that its traversals took."""
    ix = build_index(data)
    asked = (selector.gen_knn_queries(data, m, 1, 1000) if operation == "knn" else selector.gen_radius_queries(data, m)).cache()
    return ix, asked, selector.label_queries(ix, asked, operation, cost, "pivot").cache()


def W14(spark: SparkSession, sf_dir: str, m: int = 1000) -> DataFrame:
    """Labels of the generated queries, by time and by work: share of each strategy, and the three parts' sizes."""
    data, rows = _view(spark, sf_dir, "li3"), []
    asked = selector.gen_knn_queries(data, m, 1, 1000).cache()
    costs = selector.strategy_costs(build_index(data), asked, child_order="pivot").cache()  # one run is both labels
    for cost in ("time", "work"):
        rows += [("W14", "li3", STRATEGIES[r.label], f"queries_by_{cost}", r["count"]) for r in selector.cheapest(costs, cost).groupBy("label").count().collect()]
    rows += [("W14", "li3", name, "queries", part.count()) for name, part in zip(("train", "validation", "test"), selector.split_80_10_10(asked), strict=True)]
    return _frame(spark, rows)


def W15(spark: SparkSession, sf_dir: str, m: int = 1000, kinds: tuple[str, ...] = ("tree", "ovr", "mlp", "rf", "majority")) -> DataFrame:
    """Selectors with coordinates alone and with leaf similarities, told from held-out queries: MRR, macro and micro precision."""
    ix, asked, labels = ground_truth(_view(spark, sf_dir, "li3"), m)
    scores = []
    for which in ("f1", "f"):
        data = selector.features(ix, asked, which).join(labels.select("qid", "label"), "qid").cache()
        train, _, test = selector.split_80_10_10(data)
        for kind in kinds:
            model = selector.train_selector(train, kind)
            ranked = selector.rank_strategies(model, test).join(test.select("qid", "label"), "qid").cache()
            told = ranked.where("place = 1").select("qid", F.col("strategy").alias("prediction"), "label")
            for metric, frame in (("mrr", M.mrr(ranked)), ("macro", M.macro_precision(told)), ("micro", M.micro_precision(told))):
                scores.append((kind, which, metric, float(frame.first()[0] or 0.0)))
    gains = M.feature_gain(spark.createDataFrame(scores, "selector string, features string, metric string, value double")).collect()
    return _frame(spark, [("W15", "li3", f"{k}:{w}", name, v) for k, w, name, v in scores] + [("W15", "li3", f"{r.selector}:gain", r.metric, r.gain) for r in gains])


_RUNS: dict[tuple, list[tuple]] = {}


def _auto(spark: SparkSession, sf_dir: str, view: str, operation: str, m: int) -> list[tuple]:
    """A view's run: the selector learns from four fifths of the queries and is measured on a tenth that it has not seen."""
    key = (spark.sparkContext.applicationId, sf_dir, view, operation, m)
    if key in _RUNS:  # the two kNN figures are of one run
        return _RUNS[key]
    data = _view(spark, sf_dir, view)
    ix, asked, labels = ground_truth(data, m, operation)
    train, _, test = selector.split_80_10_10(asked)
    known = selector.features(ix, train, "f1").join(labels.select("qid", "label"), "qid")
    model = selector.train_selector(known, "rf")
    chosen, predict_s = M.timed(lambda: selector.predicted(ix, test, model, "f1"))
    fixed = search.access_log(ix, _each(test), operation, child_order="pivot").cache()
    auto, total_s = M.timed(lambda: search.access_log(ix, chosen, operation, child_order="pivot").cache().collect())
    auto = spark.createDataFrame(auto)
    rows = [(view, r.strategy, "points_accessed", r.mean_points_accessed) for r in M.points_accessed(fixed).collect()]
    rows += [(view, r.strategy, "mean_us", r.mean_us) for r in M.query_time(fixed).collect()]
    mean = auto.agg(F.avg("points_accessed"), F.avg("elapsed_us"), F.count("*")).first()
    told_us = 1e6 * predict_s / max(mean[2], 1)
    share = M.selection_share(chosen).first()
    rows += [(view, "auto", "points_accessed", mean[0]), (view, "auto", "mean_us", mean[1]), (view, "auto", "mean_us_with_prediction", mean[1] + told_us), (view, share.strategy, "selected_share", share.share)]
    rows += [(view, "auto", "prediction_share", M.prediction_share(predict_s, predict_s + total_s)), (view, "auto", "gain_over_mean", M.gain_over_mean(fixed, auto, "elapsed_us").first().gain)]
    if operation == "knn":  # the other indexes, each by its own strategy
        for name, strategy in (("binary_kd", "box_dfs"), ("ball", "ball_dfs"), ("rtree", "box_bfs")):
            s, n = _cost(_builders()[name](data), test, operation, strategy)
            rows += [(view, name, "points_accessed", n), (view, name, "mean_us", 1e6 * s / max(mean[2], 1))]
    for table in (data, asked, labels, fixed):
        table.unpersist()
    _RUNS[key] = rows
    return rows


def W16(spark: SparkSession, sf_dir: str, m: int = 1000, views: tuple[str, ...] = EIGHT) -> DataFrame:
    """kNN time: the selector against the fixed strategies and other indexes."""
    return _frame(spark, [("W16", *r) for v in views for r in _auto(spark, sf_dir, v, "knn", m) if r[2] in ("mean_us", "mean_us_with_prediction", "gain_over_mean")])


def W17(spark: SparkSession, sf_dir: str, m: int = 1000, views: tuple[str, ...] = EIGHT) -> DataFrame:
    """kNN points accessed."""
    return _frame(spark, [("W17", *r) for v in views for r in _auto(spark, sf_dir, v, "knn", m) if r[2] == "points_accessed"])


def W18(spark: SparkSession, sf_dir: str, m: int = 1000, views: tuple[str, ...] = EIGHT) -> DataFrame:
    """Radius search: dominant strategy, its share, prediction share, gain over the mean strategy."""
    return _frame(spark, [("W18", *r) for v in views for r in _auto(spark, sf_dir, v, "radius", m) if r[2] in ("selected_share", "prediction_share", "gain_over_mean")])


def W19(spark: SparkSession, sf_dir: str, k: int = 10, iters: int = 5) -> DataFrame:
    """k-means by Lloyd, by an index of the centroids and by whole nodes of the fast and the base tree: time, SSE, distance tests; embeddings against their labels."""
    data, rows = _view(spark, sf_dir, "li2"), []
    fast, base = build_index(data, mode="inverse"), build_index(data, mode="sort")
    for name, source, mode in (("lloyd", data, "lloyd"), ("centroid_index", data, "centroid_index"), ("node_filter", fast, "node_filter"), ("node_filter_base", base, "node_filter")):
        out, s = M.timed(lambda source=source, mode=mode: kmeans.run(source, k, iters, mode))
        rows += [("W19", "li2", name, "seconds", s), ("W19", "li2", name, "sse", out["history"][-1]["sse"]), ("W19", "li2", name, "distance_tests", out["history"][-1]["tests"])]
    emb = _view(spark, sf_dir, "emb64")
    out = kmeans.run(emb, k, iters)
    told = kmeans.assigned(emb, out["centroids"]).join(table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("pid"), "label"), "pid")
    purity = told.groupBy("cid", "label").count().groupBy("cid").agg(F.max("count").alias("top")).agg(F.sum("top")).first()[0]
    rows += [("W19", "emb64", "lloyd", "sse", out["history"][-1]["sse"]), ("W19", "emb64", "lloyd", "purity", purity / emb.count())]
    return _frame(spark, rows)


def W20(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Path metric: two of three levels shared, none, all."""
    cases = [([0, 1, 0], [0, 1, 2]), ([0, 1, 0], [2, 1, 0]), ([0, 1, 0], [0, 1, 0])]
    frame = spark.createDataFrame([(i, *c) for i, c in enumerate(cases)], "i int, a array<int>, b array<int>")
    return frame.select(F.lit("W20").alias("workload"), F.lit("fixture").alias("dataset"), F.col("i").cast("string").alias("config"), F.lit("similarity").alias("metric"), selector.path_similarity(F.col("a"), F.col("b")).cast("double").alias("value"))


def W21(spark: SparkSession, sf_dir: str, batches: int = 10) -> DataFrame:
    """Events as a stream of files: after each micro-batch the newest point is asked for and answered at distance 0."""
    import time

    from pivotgrove.queries import write_in_order

    events, data, rows = table(spark, sf_dir, "events"), _view(spark, sf_dir, "evt2"), []
    n = int(0.8 * (data.agg(F.max("pid")).first()[0] + 1))
    folder = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    write_in_order(events.where(F.col("event_id") >= n).withColumn("event_id", F.col("event_id") - n), folder, batches)
    began = [time.perf_counter()]

    def fresh(ix: IndexHandle) -> None:
        took, i = time.perf_counter() - began[0], ix.version - 1
        newest = data.join(ix.points().agg(F.max("pid").alias("pid")), "pid").select(F.col("pid").alias("qid"), F.col("coords").alias("qcoords"), F.lit(1).alias("k"))
        rows.extend([("W21", "evt2", f"batch {i}", "insert_s", took), ("W21", "evt2", f"batch {i}", "newest_dist", search.knn(ix, newest).first().dist)])
        began[0] = time.perf_counter()

    stream = ingest.events_stream(spark, folder).withColumn("event_id", F.col("event_id") + n)
    ingest.stream_insert(stream, ingest.IndexHolder(build_index(data.where(F.col("pid") < n), t=4), fresh), f"{folder}-checkpoint").awaitTermination()
    return _frame(spark, rows)


ALL = {f"W{i}": globals()[f"W{i}"] for i in range(1, 22)}
