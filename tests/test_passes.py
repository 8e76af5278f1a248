"""A build's passes over the points, and the first bounds of many queries, against plain loops."""

import math

import numpy as np
from pyspark.sql import functions as F

from pivotgrove.operators import index, search, tree
from pivotgrove.sources import points as P


def _mixed(spark):
    rows = [(i, [float(i % 97), float(i % 89)]) for i in range(5000)]
    bad = [(None, [1.0, 2.0]), (9001, None), (9002, [math.nan, 1.0]), (9003, [1.0, math.inf]), (9004, [None, 1.0]), (9005, [-math.inf, 0.0])]
    return spark.createDataFrame(rows + bad, "pid long, coords array<double>").repartition(5)


def test_a_pass_counts_draws_and_leaves_out_rows_that_are_no_points(spark):
    data = _mixed(spark)
    good = {r.pid: r.coords for r in P.validate(data)[0].collect()}
    n, d, ids, sample = index.counted(data.withColumn("draw", F.pmod("pid", F.lit(10))), 3)
    assert (n, d) == (len(good), 2) == (5000, 2)
    assert ids.tolist() == sorted(i for i in good if i % 10 < 3) and sample.tolist() == [good[i] for i in ids.tolist()]
    ix = index.build_index(data, cell_points=500)
    assert sorted(r.pid for r in ix.points().select("pid").collect()) == sorted(good)


def test_cell_ends_are_summed_in_the_tasks(spark):
    data, points = _mixed(spark), np.array([[i % 97, i % 89] for i in range(5000)], dtype=float)
    upper = index.upper_tree(points, np.arange(5000), 12, tree.Params(t=4))
    cell = tree.Router.of(upper).cells(points)
    got = index.cell_ends(data, upper, 2)
    plan = got._jdf.queryExecution().executedPlan().toString()
    assert "array_contains" not in plan  # coordinates are computed once a row, not for each test of them
    want = {c: (int((cell == c).sum()), *points[cell == c].min(0), *points[cell == c].max(0)) for c in np.unique(cell).tolist()}
    assert {r.cell: (r.held, r.l0, r.l1, r.h0, r.h1) for r in got.collect()} == want


def test_bounds_by_the_marks_of_many_cells_are_those_of_a_loop():
    draw = np.random.default_rng(1)
    for d in (1, 2, 4):
        each = [np.concatenate([draw.integers(1, 50, (c, 1)).astype(float), np.sort(draw.random((c, 2, d)), 1).reshape(c, 2 * d)], 1) for c in (0, 1, 3, 600, *draw.integers(0, 90, 20))]
        many = np.array([len(m) for m in each])
        q, home, k, bound = draw.random((800, d)), draw.integers(0, len(each), 800), draw.integers(1, 900, 800), np.where(draw.random(800) < 0.3, np.inf, draw.random(800))
        want = bound.copy()
        for i, m in enumerate(each[h] for h in home):
            far = np.sqrt((np.maximum(np.abs(q[i] - m[:, 1 : d + 1]), np.abs(q[i] - m[:, d + 1 :])) ** 2).sum(1))
            order = np.argsort(far)
            enough = np.flatnonzero(np.cumsum(m[order, 0]) >= k[i])
            if len(enough):
                want[i] = min(want[i], far[order][enough[0]])
        np.testing.assert_allclose(search._finer(bound, home, (np.concatenate(each), np.cumsum(many) - many, many), q, k), want, rtol=1e-12)


def test_walks_that_go_alone_have_the_answers_and_counters_of_the_tree():
    draw = np.random.default_rng(5)
    for d, n in ((2, 900), (3, 700)):
        points, pids = np.round(draw.random((n, d)) * 12), draw.permutation(n) - 100
        points[: n // 4] = points[0]  # many equal points: ties go by pid
        root = tree.build(points, pids, tree.Params(c=9, t=4))
        packed = tree.pack(root, points, pids)
        held, lone = tree.unpack(packed), tree.Lone(packed)
        for q in [*points[:: n // 6], np.full(d, 30.0)]:
            for k in (1, 10, 150, n - 1):
                for s in tree.STRATEGIES:
                    for order in ("nearest", "pivot"):
                        for limit, budget, single in ((np.inf, None, "own"), (4.0, None, "single"), (6.0, 60, "own")):
                            a, b = tree.nearest(*held, q, k, s, order, limit, budget, single), lone.nearest(q, k, s, order, limit, budget, single)
                            assert sorted(zip(a[1], a[0])) == sorted(zip(b[1], b[0])) and a[2] == b[2]


def test_searches_ask_an_index_once_for_its_totals(spark, sf_dir):
    data = P.points(spark, sf_dir, "ord2")
    ix = index.build_index(data, cell_points=300)
    asked = search.prepared(data.limit(20).select(F.col("pid").alias("qid"), F.col("coords").alias("qcoords"), F.lit(5).alias("k")), "box_dfs")
    search.probes(ix, asked, True)
    spark.sparkContext.setJobGroup("totals", "totals")
    search.probes(ix, asked, True)
    jobs = spark.sparkContext.statusTracker().getJobIdsForGroup("totals")
    spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)
    assert len(jobs) <= 1  # the cells themselves; a count, a sum and the marks were jobs of their own
    assert ix.totals() == (ix.cells.count(), data.count(), ix.cells.agg(F.sum(F.size("marks"))).first()[0])
