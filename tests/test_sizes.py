"""What failed on tables 6 and 60 times as large, on small tables."""

import pytest
from pyspark.sql import functions as F

from pivotgrove.operators import relational
from pivotgrove.sources import points as P


def test_pairs_meet_once_and_by_exchange(spark, sf_dir):
    pairs = relational.replicated_pairs(P.points(spark, sf_dir, "cus2"), 50.0)
    plan = pairs._jdf.queryExecution().executedPlan().toString()
    assert "Broadcast" not in plan and "Aggregate" not in plan
    assert pairs.count() == pairs.distinct().count() > 0


def test_stream_dedupe_keeps_rows_in_files_and_takes_events_by_time(spark, tmp_path):
    """Ids that do not follow time: dealt by id, the second half came behind the watermark and was lost."""
    from pivotgrove.queries import QUERIES, table

    events = table(spark, "/root/testdata/sf0.001", "events")
    twice = events.unionByName(events.withColumn("event_id", F.col("event_id") + 1_000_000))
    twice.write.parquet(str(tmp_path / "events.parquet"))
    before = {t.name for t in spark.catalog.listTables()}
    assert QUERIES["stream_dedupe"](spark, str(tmp_path)).first().n == 2 * events.count()
    assert {t.name for t in spark.catalog.listTables()} == before  # no table in the driver's memory


def test_marks_bound_the_first_wave(spark, sf_dir):
    """A query's first bound is that of a few hundred points, not of a whole cell; answers stay exact."""
    from pivotgrove.baselines import brute
    from pivotgrove.operators import search
    from pivotgrove.operators.index import build_index

    data = P.points(spark, "/root/testdata/sf0.01", "ord2")
    asked = data.where("pid % 500 = 0").select(F.col("pid").alias("qid"), F.col("coords").alias("qcoords"), F.lit(10).cast("long").alias("k"))
    ix = build_index(data, cell_points=4000)
    assert search.probes(ix, search.prepared(asked, "box_dfs"), True).count() < 2 * asked.count()
    for how in ({"strategy": "ball_bfs"}, {"strategy": "box_dfs", "home_pass": True}, {"strategy": "box_bfs", "seed_bound": False}):
        assert search.knn(ix, asked, **how).exceptAll(brute.knn(data, asked)).isEmpty()


def test_brute_knn_in_arrays(spark):
    """No pairs in the plan: each task hands on k rows a query; ties by id, more than there are, rows that are no points."""
    from pivotgrove.baselines import brute

    data = spark.createDataFrame([(i, [float(i % 5), 0.0]) for i in range(40)] + [(99, [float("nan"), 0.0])], P.POINT_SCHEMA)
    asked = spark.createDataFrame([(1, [1.2, 0.0], 3), (2, [4.0, 0.0], 100), (3, [0.0, 0.0], 0)], "qid long, qcoords array<double>, k long")
    out = brute.knn(data, asked)
    assert "NestedLoop" not in out._jdf.queryExecution().executedPlan().toString()
    rows = sorted((r.qid, r["rank"], r.pid, r.dist) for r in out.collect())
    assert [r[2] for r in rows if r[0] == 1] == [1, 6, 11] and abs(rows[0][3] - 0.2) < 1e-12
    assert len([r for r in rows if r[0] == 2]) == 40 and {r[0] for r in rows} == {1, 2}


def test_early_stop_over_several_cells(spark, sf_dir):
    from pivotgrove.operators import selector
    from pivotgrove.operators.index import build_index

    data = P.points(spark, sf_dir, "ord2")
    ix = build_index(data, cell_points=300)
    asked = data.where("pid % 50 = 0").select(F.col("pid").alias("qid"), F.col("coords").alias("qcoords"), F.lit(10).cast("long").alias("k"))
    early, full = selector.label_early_stop(ix, asked), selector.label_queries(ix, asked).select("qid", "label")
    assert ix.cells.count() > 1 and early.count() == asked.count() and early.exceptAll(full).isEmpty()


def test_all_points_asked_for_need_no_order(spark, sf_dir):
    from pivotgrove.operators import search
    from pivotgrove.operators.index import build_index

    data = P.points(spark, "/root/testdata/sf0.01", "cus2")
    asked = data.where("pid % 500 = 0").select(F.col("pid").alias("qid"), F.col("coords").alias("qcoords"), F.lit(10**6).cast("long").alias("k"))
    counted = search.knn(build_index(data, cell_points=400), asked).groupBy("qid").count()
    assert "Window" not in counted._jdf.queryExecution().executedPlan().toString()
    assert {r["count"] for r in counted.collect()} == {data.count()}


ON_TABLES = ["fanout_table", "fanout_best", "fanout_solvers", "fanout_example8", "balance_audit", "config_ratio", "feature_gain", "factor_ratios_fixture"]


@pytest.mark.parametrize("name", ON_TABLES)
def test_measures_read_a_given_table(spark, sf_dir, name):
    import duckdb

    from pivotgrove.queries import ORACLES, QUERIES

    assert " from orders" in ORACLES[name] or " from part" in ORACLES[name]
    con = duckdb.connect()
    for t in ("orders", "part"):
        con.execute(f"create view {t} as select * from '{sf_dir}/{t}.parquet'")
    got, want = QUERIES[name](spark, sf_dir).toPandas(), con.execute(ORACLES[name]).df()
    order = lambda df: df[sorted(got.columns)].astype(str).sort_values(sorted(got.columns)).reset_index(drop=True)
    assert order(got).equals(order(want)) and len(got)


def test_long_texts_reach_kernels_in_bounded_batches(spark):
    from pivotgrove import runtime

    def sizes(batches):
        import pyarrow as pa

        for batch in batches:
            yield pa.RecordBatch.from_pydict({"n": [batch.nbytes]})

    runtime.ship(spark)
    rows = spark.range(0, 4000, 1, 1).select(F.repeat(F.lit("word "), 1000).alias("text"))
    got = [r.n for r in rows.mapInArrow(runtime.giving_back(sizes), "n long").collect()]
    assert sum(got) > 4000 * 5000 and max(got) < 8_000_000


def test_walks_side_by_side_are_the_same_walks():
    """Answers and counters of each walk, all strategies, with ties, leaves of equal points, limits and budgets."""
    import numpy as np

    from pivotgrove.operators import tree

    draw = np.random.default_rng(5)
    points = np.repeat(np.round(draw.normal(size=(60, 3)) * 9), 40, axis=0)
    pids = draw.permutation(len(points)).astype(np.int64)
    root = tree.build(points, pids, tree.Params(t=4))
    flat = tree.Flat.of(tree.pack(root, points, pids))
    q, k = points[draw.integers(0, len(points), 50)] + draw.normal(size=(50, 3)), draw.integers(1, 9, 50)
    limit, budget = np.where(draw.random(50) < 0.5, np.inf, draw.random(50) * 15), draw.integers(5, 900, 50)
    for strategy in tree.STRATEGIES:
        for some in (None, budget):
            found, work = tree.nearest_together(flat, q, k, limit, strategy, budget=some)
            for i in range(50):
                near, far, w = tree.nearest(root, points, pids, q[i], int(k[i]), strategy, limit=limit[i], budget=None if some is None else int(some[i]))
                assert sorted(zip(found[i][1], found[i][0], strict=True)) == sorted(zip(far, near, strict=True))
                assert work[i].tolist() == [w.nodes_visited, w.leaves_visited, w.points_accessed, w.pruned_nodes]


def test_queries_of_one_cell_are_many_tasks(spark, sf_dir):
    """A small index left all queries of its only cell to one task."""
    from pivotgrove.operators import search
    from pivotgrove.operators.index import build_index

    data = P.points(spark, sf_dir, "ord2")
    asked = data.select(F.col("pid").alias("qid"), F.col("coords").alias("qcoords"), F.lit(10).cast("long").alias("k"))
    ix = build_index(data)
    met = search.access_log(ix, asked).groupBy(F.spark_partition_id()).count()
    rows = search.visits(ix, search.prepared(asked, "box_dfs"), True).select(F.spark_partition_id().alias("task")).distinct().count()
    assert ix.cells.count() == 1 and rows > 2 and met.agg(F.sum("count")).first()[0] == asked.count()


def test_labels_by_time_and_by_work_are_of_one_run(spark, sf_dir, monkeypatch):
    from pivotgrove import workloads
    from pivotgrove.operators import selector
    from pivotgrove.operators.index import build_index

    runs, visits = [], selector.visits
    monkeypatch.setattr(selector, "visits", lambda *a, **k: runs.append(1) or visits(*a, **k))
    rows = workloads.W14(spark, sf_dir, m=20).collect()
    assert len(runs) == 1 and {r.metric for r in rows} == {"queries_by_time", "queries_by_work", "queries"}
    data = P.points(spark, sf_dir, "li3")
    ix, asked = build_index(data), selector.gen_knn_queries(data, 20, 1, 1000)
    work = selector.cheapest(selector.strategy_costs(ix, asked), "work").select("qid", "label")
    assert work.count() == 20 and work.exceptAll(selector.label_queries(ix, asked).select("qid", "label")).isEmpty()


def test_radius_walks_on_arrays_are_the_same_walks():
    """Answers and counters of all strategies, whole nodes accepted or not, with ties, empty children and a root that is a leaf."""
    import numpy as np

    from pivotgrove.operators import tree

    draw = np.random.default_rng(6)
    many = np.repeat(np.round(draw.normal(size=(60, 3)) * 9), 40, axis=0)
    for points, params in ((many, tree.Params(t=4)), (draw.normal(size=(3000, 2)) ** 3, tree.Params(t=8, mode="equal_width")), (many[:20], tree.Params())):
        pids = draw.permutation(len(points)).astype(np.int64)
        root = tree.build(points, pids, params)
        lone = tree.Lone(tree.pack(root, points, pids))
        for strategy in tree.STRATEGIES:
            for i in range(20):
                q, r = points[draw.integers(0, len(points))] + draw.normal(size=points.shape[1]) * (i % 3), (0.0, 0.5, 3.0, 200.0)[i % 4]
                for accept in (False, True):
                    want, got = tree.radius_search(root, points, pids, q, r, strategy, accept), lone.within(q, r, strategy, accept)
                    assert sorted(zip(want[0], want[1], strict=True)) == sorted(zip(got[0], got[1], strict=True)) and want[2] == got[2]
                for limit in (np.inf, r):  # all points asked for
                    want, got = (f(q, len(points), strategy, limit=limit) for f in (lambda *a, **k: tree.nearest(root, points, pids, *a, **k), lone.nearest))
                    assert sorted(zip(want[0], want[1], strict=True)) == sorted(zip(got[0], got[1], strict=True)) and want[2] == got[2]


def test_a_log_carries_no_answers(spark, sf_dir):
    """Counters came back beside every answer, which nothing read."""
    from pivotgrove.operators import search
    from pivotgrove.operators.index import build_index

    data = P.points(spark, sf_dir, "ord2")
    asked = data.where("pid % 50 = 0").select(F.col("pid").alias("qid"), F.col("coords").alias("qcoords"), F.lit(500.0).alias("r"), F.lit(10).cast("long").alias("k"))
    ix = build_index(data, cell_points=400)
    for knn in (True, False):
        every = search.visits(ix, search.prepared(asked, "box_dfs"), knn)
        log, answers = (search.visits(ix, search.prepared(asked, "box_dfs"), knn, only=x) for x in ("log", "answers"))
        counters = ["qid", "nodes_visited", "leaves_visited", "points_accessed", "pruned_nodes"]
        assert log.count() > 0 and log.select(counters).exceptAll(every.where("pid is null").select(counters)).isEmpty() and log.where("pid is not null").isEmpty()
        assert answers.columns == ["qid", "pid", "dist"] and answers.count() > 0 and every.where("pid is not null").select(answers.columns).exceptAll(answers).isEmpty()


def test_all_points_asked_for_move_few_copies(spark, monkeypatch):
    """Each block of two queries took a copy of every cell through an exchange."""
    from pivotgrove.operators import search
    from pivotgrove.operators.index import build_index

    monkeypatch.setattr(search, "QUERY_BLOCK", 10)
    monkeypatch.setattr(search, "MOVED_POINTS", 3000)
    blocks, at_cells = [], search.at_cells
    monkeypatch.setattr(search, "at_cells", lambda *a, **k: blocks.append(k["block"]) or at_cells(*a, **k))
    data = P.points(spark, "/root/testdata/sf0.01", "cus2")
    asked = data.where("pid % 10 = 0").select(F.col("pid").alias("qid"), F.col("coords").alias("qcoords"), F.lit(10**6).cast("long").alias("k"))
    got = {r["count"] for r in search.knn(build_index(data, cell_points=400), asked).groupBy("qid").count().collect()}
    n = data.count()
    assert got == {n} and len(blocks) == 1 and -(-asked.count() // blocks[0]) * n <= 3000


def test_brute_knn_far_from_the_origin():
    """Squares told by a product lose digits there: what is in reach is told exactly, ties and coordinates whose squares overflow too."""
    import numpy as np
    import pyarrow as pa

    from pivotgrove.baselines import brute

    draw = np.random.default_rng(3)
    for d, scale in ((2, 4e5), (64, 1.0), (2, 1e9), (2, 1e200)):
        points = np.repeat(draw.normal(size=(500, d)), 6, axis=0)[draw.permutation(3000)] + scale
        q, k = np.vstack((points[:100], draw.normal(size=(50, d)) + scale)), draw.integers(1, 30, 150)
        shared = type("", (), {"value": (np.arange(150), q, k)})
        parts = [slice(a, a + 700) for a in range(0, 3000, 700)]
        batches = [pa.RecordBatch.from_arrays([pa.array(np.arange(3000)[p]), pa.array(points[p].tolist(), pa.list_(pa.float64()))], ["pid", "coords"]) for p in parts]
        got = pa.Table.from_batches(list(brute._nearest(shared, d)(iter(batches)))).to_pydict()
        want = []
        for i in range(150):
            square = np.zeros(3000)
            for j in range(d):
                square += (points[:, j] - q[i, j]) ** 2
            best = np.lexsort((np.arange(3000), np.sqrt(square)))[: k[i]]
            want += [(i, int(p), float(np.sqrt(square[p]))) for p in best]
        assert list(zip(got["qid"], got["pid"], got["dist"], strict=True)) == want
