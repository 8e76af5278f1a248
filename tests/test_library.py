"""The library's queries: SQL equality on the small tables, stores, streams, files, selectors."""

import glob
import os

import duckdb
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

import __spark_entry__
from pivotgrove.baselines import brute
from pivotgrove.operators import insertion, kmeans, search, selector
from pivotgrove.operators.index import build_index
from pivotgrove.queries import ORACLES, QUERIES
from pivotgrove.runtime import components
from pivotgrove.sources import points as P
from pivotgrove.sources import store

CHECKED = ["geo_dist_orders", "geo_box_bounds", "geo_ball_bounds", "fanout_table", "fanout_best", "tree_exact_t3_assign", "pivots_disc", "pivots_rank_corrected", "cdf_root_fit", "cdf_predict", "cdf_incremental_refit", "knn_box_dfs", "knn_ball_bfs", "knn_4d", "radius_box_bfs", "rebuild_selective_knn", "rebuild_range_fixture", "path_metric_fixture", "kmeans_filtered_3iters", "baseline_ball_knn", "baseline_forest_knn", "grid_radius", "as_of_events", "win_range_1d_radius", "stream_insert_knn"]


@pytest.fixture(scope="module")
def sql(sf_dir):
    con = duckdb.connect()
    for p in glob.glob(f"{sf_dir}/*.parquet"):
        con.execute(f"create view {os.path.basename(p)[:-8]} as select * from '{p}'")
    return con


@pytest.mark.parametrize("name", CHECKED)
def test_query_equals_sql(spark, sf_dir, sql, name):
    got, want = QUERIES[name](spark, sf_dir).toPandas(), sql.execute(ORACLES[name]).df()
    columns = sorted(got.columns)
    assert columns == sorted(want.columns)
    order = lambda df: df[columns].astype(str).sort_values(columns).reset_index(drop=True)
    assert order(got).equals(order(want))


def test_entry_and_names(spark):
    assert __spark_entry__.entry(spark).count() > 0
    assert set(ORACLES) <= set(QUERIES)


def test_store_files_and_quarantine(spark, sf_dir, tmp_path):
    data = P.points(spark, sf_dir, "part2")
    ix = build_index(data, cell_points=60)
    store.save(ix, str(tmp_path / "ix"))
    newer = insertion.insert_batch(ix, data.select((F.col("pid") + 10_000).alias("pid"), "coords"))
    store.save(newer, str(tmp_path / "ix"))
    n = data.count()
    assert store.load(spark, str(tmp_path / "ix"), 0).points().count() == n
    assert store.load(spark, str(tmp_path / "ix")).points().count() == 2 * n
    P.write_points(data, str(tmp_path / "csv"), "csv")
    assert P.read_points(spark, str(tmp_path / "csv")).exceptAll(data).count() == 0
    odd = spark.createDataFrame([(1, [1.0, 2.0]), (2, [float("nan"), 1.0]), (3, None), (None, [1.0, 1.0])], P.POINT_SCHEMA)
    good, bad = P.validate(odd)
    assert good.count() == 1 and bad.count() == 3


def test_empty_index_large_k_and_bad_k(spark, sf_dir):
    none = spark.createDataFrame([], P.POINT_SCHEMA)
    asked = spark.createDataFrame([(1, [0.0, 0.0], 5)], "qid long, qcoords array<double>, k int")
    assert search.knn(build_index(none), asked).count() == 0
    data = P.points(spark, sf_dir, "cus2")
    ix = build_index(data, cell_points=40)
    assert search.knn(ix, asked.withColumn("k", F.lit(10**6))).count() == data.count()
    assert search.knn(ix, asked.withColumn("k", F.lit(0))).count() == 0


def test_same_tree_for_any_partitioning(spark, sf_dir):
    data = P.points(spark, sf_dir, "ord2")
    shape = lambda df: sorted(build_index(df, cell_points=400).nodes().select("cell_id", "node_id", "n_points", "radius").collect())
    assert shape(data.repartition(1)) == shape(data.repartition(7))


def test_selector_early_stop_and_dispatch(spark, sf_dir):
    data = P.points(spark, sf_dir, "ord2")
    ix = build_index(data)
    asked = selector.gen_knn_queries(data, 40, 1, 20).cache()
    labels = selector.label_queries(ix, asked)
    early = selector.label_early_stop(ix, asked).withColumnRenamed("label", "early")
    assert labels.join(early, "qid").where("label != early").count() == 0
    rows = selector.features(ix, asked, "f").join(labels, "qid").select("features", "label")
    got = selector.auto_search(ix, asked, selector.train_selector(rows, "majority"))
    assert got.select("qid", "pid").exceptAll(brute.knn(data, asked).select("qid", "pid")).count() == 0


def test_kmeans_forms_agree(spark, sf_dir):
    data = P.points(spark, sf_dir, "evt2")
    ix = build_index(data, cell_points=300)
    runs = [kmeans.run(s, 5, 4, m) for s, m in ((data, "lloyd"), (data, "centroid_index"), (ix, "node_filter"))]
    for r in runs[1:]:
        assert abs(r["centroids"] - runs[0]["centroids"]).max() < 1e-6 and (r["sizes"] == runs[0]["sizes"]).all()
    assert runs[2]["history"][-1]["tests"] <= runs[0]["history"][-1]["tests"]


def test_components_of_a_path_a_star_and_none(spark):
    path = [(i, i + 1) for i in range(100, 160)] + [(1, 900), (900, 901), (5, 5)]
    got = {r.node: r.root for r in components(spark.createDataFrame(path, "src long, dst long").repartition(7)).collect()}
    assert all(got[i] == 100 for i in range(100, 161)) and got[901] == got[900] == got[1] == 1 and 5 not in got
    assert components(spark.createDataFrame([], "src long, dst long")).count() == 0


def test_rebuild_log_holds_every_rebuild(spark, tmp_path, monkeypatch):
    data = spark.range(400).select(F.col("id").alias("pid"), F.array(F.rand(1), F.rand(2)).alias("coords"))
    one = {"depth": 0, "i0": 0, "i1": 1, "points_rebuilt": 2, "points_full": 3, "reason": "test"}
    merge = insertion._merge

    def many(*a):  # a batch that causes 12,000 rebuilds in every cell it touches
        kernel = merge(*a)

        def told(left, right):
            out = kernel(left, right)
            return out.set_column(out.schema.get_field_index("log"), "log", pa.array([[one] * 12_000] * out.num_rows, insertion._LOG_ARROW))

        return told

    ix = build_index(data)
    monkeypatch.setattr(insertion, "_merge", many)
    newer = insertion.insert_batch(ix, data.select((F.col("pid") + 1_000).alias("pid"), "coords"))
    touched = newer.cells.count()
    assert insertion.rebuild_log(ix, spark).count() == 0
    assert insertion.rebuild_log(newer, spark).count() == 12_000 * touched
    store.save(newer, str(tmp_path / "ix"))
    kept = insertion.rebuild_log(store.load(spark, str(tmp_path / "ix")), spark)
    assert kept.count() == 12_000 * touched and kept.agg(F.sum("points_full")).first()[0] == 36_000 * touched


def test_similarity_features_reach_every_cell(spark, sf_dir):
    from pivotgrove.operators import selector
    from pivotgrove.operators.index import build_index
    from pivotgrove.sources.points import points

    data = points(spark, sf_dir, "ord2")
    ix = build_index(data, cell_points=40)  # more cells than prefixes
    assert len(selector.upper_paths(ix)) > 16
    asked = data.where("pid % 50 = 0").selectExpr("pid as qid", "coords as qcoords", "10 as k")
    got = [tuple(r.f2) for r in selector.features_f2(ix, asked, most=16).collect()]
    assert len({len(x) for x in got}) == 1 and len(got[0]) <= 16 and all(max(x) > min(x) for x in got)
    assert len(set(got)) > 4
