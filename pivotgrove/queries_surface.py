"""Queries of the user's surface, of measures on small fixtures, and of variants beside the main ones."""

from __future__ import annotations

import uuid
from functools import partial

from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from pivotgrove import metrics as M
from pivotgrove import surface
from pivotgrove.operators import insertion, kmeans, relational, search, selector, tree
from pivotgrove.operators.index import build_index
from pivotgrove.plans import cdf
from pivotgrove.queries import _KM, ORACLES, SQL_VIEW, _asked, _knn, _shown, _sq, _streamed, knn_sql, query, radius_sql, write_by_time
from pivotgrove.runtime import shared_dir
from pivotgrove.sources import store
from pivotgrove.sources.points import points, table
from pivotgrove.streaming import ingest

# --- variants of the tree and of its search ----------------------------------------------------------------------

for _name, _options in {"stop_lt": {"stop": "lt"}, "split_widest": {"split": "widest"}, "split_variance": {"split": "max_variance"}, "per_node_fanout": {"t": "per_node"}, "binary": {"t": 2}, "kappa_zero": {"mode": "candidate_median", "kappa": 0.0}, "sub_squares": {"sub": "squares", "small": 0}}.items():
    query(f"knn_{_name}", knn_sql("ord2", 100, 10))(partial(_knn, "ord2", 100, "box_dfs", **_options))


@query("knn_many_cells", knn_sql("ord2", 100, 10))
def knn_many_cells(spark, sf_dir):
    data = points(spark, sf_dir, "ord2")
    return _shown(search.knn(build_index(data, cell_points=100), _asked(data, 100), "box_dfs"))


@query("knn_unseeded_bfs", knn_sql("ord2", 100, 10))
def knn_unseeded_bfs(spark, sf_dir):
    data = points(spark, sf_dir, "ord2")
    return _shown(search.knn(build_index(data, cell_points=4000), _asked(data, 100), "box_bfs", seed_bound=False))


@query("knn_single_bound_dfs", knn_sql("ord2", 100, 10))
def knn_single_bound_dfs(spark, sf_dir):
    data = points(spark, sf_dir, "ord2")
    return _shown(search.knn(build_index(data, cell_points=4000), _asked(data, 100), "ball_dfs", dfs_bound="single"))


@query("knn_more_than_points", f"with p as ({SQL_VIEW['cus2'][1]}) select q.pid as qid, count(*) as n from p, p as q where q.pid % 100 = 0 group by 1")
def knn_more_than_points(spark, sf_dir):
    data = points(spark, sf_dir, "cus2")
    return search.knn(build_index(data), _asked(data, 100, 1_000_000)).groupBy("qid").agg(F.count("*").alias("n"))


@query("knn_below_one", "select 0::BIGINT as n")
def knn_below_one(spark, sf_dir):
    data = points(spark, sf_dir, "cus2")
    return search.knn(build_index(data), _asked(data, 100, 0)).agg(F.count("*").alias("n"))


@query("insert_check_before_knn", knn_sql("evt2", 100, 10))
def insert_check_before_knn(spark, sf_dir):
    data = points(spark, sf_dir, "evt2")
    n = data.agg(F.max("pid")).first()[0] + 1
    ix = build_index(data.where(F.col("pid") < int(0.8 * n)), t=4, cell_points=4000, check="before")
    return _shown(search.knn(insertion.insert_batch(ix, data.where(F.col("pid") >= int(0.8 * n))), _asked(data, 100)))


@query("insert_one_by_one_knn", knn_sql("part2", 100, 10))
def insert_one_by_one_knn(spark, sf_dir):
    data = points(spark, sf_dir, "part2")
    last = data.agg(F.max("pid")).first()[0] - 3
    ix = insertion.insert_batch(build_index(data.where(F.col("pid") <= last)), data.where(F.col("pid") > last), bulk=False)
    return _shown(search.knn(ix, _asked(data, 100)))


@query("insert_many_versions_knn", knn_sql("evt2", 100, 10))
def insert_many_versions_knn(spark, sf_dir):
    data = points(spark, sf_dir, "evt2")
    ix = build_index(data.where("pid % 10 != 0"), t=4, cell_points=4000)
    for i in range(9):  # past one compaction
        ix = insertion.insert_batch(ix, data.where(f"pid % 10 = 0 and pid % 90 = {10 * i}"))
    return _shown(search.knn(ix, _asked(data, 100)))


# --- the user's surface ------------------------------------------------------------------------------------------


@query("knn_with_payload", f"with p as ({SQL_VIEW['cus2'][1]}), s as (select s_suppkey, s_name, s_acctbal as x0, s_nationkey::DOUBLE as x1 from supplier), r as (select s_suppkey, s_name, p.pid as c_custkey, {_sq('s', 'p', 2)} as dist from s, p), n as (select *, row_number() over (partition by s_suppkey order by dist, c_custkey) as n from r) select s_suppkey, s_name, c_custkey, c_name, cast(n as integer) as rank, dist from n join customer using (c_custkey) where n <= 2")
def knn_with_payload(spark, sf_dir):
    named = lambda t, p: table(spark, sf_dir, t).select(f"{p}key", f"{p[0]}_name", F.col(f"{p[0]}_acctbal").alias("balance"), F.col(f"{p[0]}_nationkey").alias("nation"))
    out = surface.knn_with(named("supplier", "s_supp"), named("customer", "c_cust"), 2, ["balance", "nation"], "s_suppkey", "c_custkey")
    return out.select("s_suppkey", "s_name", "c_custkey", "c_name", F.col("rank").cast("int").alias("rank"), "dist")


@query("knn_estimator", knn_sql("part2", 100, 5))
def knn_estimator(spark, sf_dir):
    data = points(spark, sf_dir, "part2")
    out = surface.NearestNeighbours(k=5).fit(data).transform(_asked(data, 100).drop("k", "r"))
    return out.select("qid", F.posexplode("neighbours").alias("at", "n")).select("qid", "n.pid", (F.col("at") + 1).alias("rank"), "n.dist")


@query("answer_arrays", f"select qid, string_agg(cast(pid as varchar), ',' order by rank) as pids from ({knn_sql('part2', 100, 5)}) group by qid")
def answer_arrays(spark, sf_dir):
    data = points(spark, sf_dir, "part2")
    rows = search.knn(build_index(data), _asked(data, 100, 5))
    return relational.answer_arrays(rows).select("qid", F.array_join(F.transform("pids", lambda x: x.cast("string")), ",").alias("pids"))


@query("sql_radius_function", f"with p as ({SQL_VIEW['ord2'][1]}), q as (select 50000.0::DOUBLE as x0, 9000.0::DOUBLE as x1) select p.pid, {_sq('p', 'q', 2)} as dist from p, q where {_sq('p', 'q', 2)} <= 900.0")
def sql_radius_function(spark, sf_dir):
    surface.register_index(spark, build_index(points(spark, sf_dir, "ord2")), "mwt")
    return spark.sql("select pid, dist from mwt_radius(array(50000D, 9000D), 900D)")


@query("sql_knn_function", f"with p as ({SQL_VIEW['ord2'][1]}), q as (select 50000.0::DOUBLE as x0, 9000.0::DOUBLE as x1) select p.pid, {_sq('p', 'q', 2)} as dist from p, q order by dist, p.pid limit 20")
def sql_knn_function(spark, sf_dir):
    surface.register_index(spark, build_index(points(spark, sf_dir, "ord2")), "mwt")
    return spark.sql("select pid, dist from mwt_knn(array(50000D, 9000D), 20)")


@query("sql_cell_function", "select count(*) as n, 0::BIGINT as elsewhere from customer")
def sql_cell_function(spark, sf_dir):
    data = points(spark, sf_dir, "cus2")
    ix = build_index(data, cell_points=200)
    surface.register_cells(spark, ix)
    data.createOrReplaceTempView("cus2_points")
    told = spark.sql("select pid, c.cell_id as told from cus2_points, lateral mwt_cell(pid, coords) c")
    return told.join(ix.points().select("pid", "cell_id"), "pid").agg(F.count("*").alias("n"), F.count_if(F.col("told") != F.col("cell_id")).alias("elsewhere"))


# --- measures on fixtures ----------------------------------------------------------------------------------------

_LOG = "(select o_orderpriority as dataset, o_orderstatus as config, count(*)::DOUBLE as value from orders group by 1, 2)"


@query("config_ratio", f"select x.dataset, x.config, x.value / z.value as ratio from {_LOG} x, {_LOG} z where x.config != 'O' and z.config = 'O' and x.dataset = z.dataset")
def config_ratio(spark, sf_dir):
    log = table(spark, sf_dir, "orders").groupBy(F.col("o_orderpriority").alias("dataset"), F.lit("orders").alias("metric"), F.col("o_orderstatus").alias("config")).agg(F.count("*").cast("double").alias("value"))
    return M.config_ratio(log, "O").select("dataset", "config", "ratio")


@query("speedup_means", "select 3.0::DOUBLE as mean, round(sqrt(2.0 * 4.0), 9) as geometric_mean")
def speedup_means(spark, sf_dir):
    return M.speedup(spark.createDataFrame([("a", 4.0, 2.0), ("b", 4.0, 1.0)], "dataset string, slow double, fast double")).select("mean", F.round("geometric_mean", 9).alias("geometric_mean"))


@query("feature_gain", "with s as (select o_orderpriority as selector, o_orderstatus as metric, o_orderkey % 2 = 0 as plain, avg(o_custkey % 10) as v from orders group by 1, 2, 3), p as (select selector, metric, max(v) filter (where plain) as f1, max(v) filter (where not plain) as f from s group by 1, 2) select *, f - f1 as gain from p")
def feature_gain(spark, sf_dir):
    kind = F.when(F.col("o_orderkey") % 2 == 0, "f1").otherwise("f")
    scores = table(spark, sf_dir, "orders").groupBy(F.col("o_orderpriority").alias("selector"), kind.alias("features"), F.col("o_orderstatus").alias("metric")).agg(F.avg(F.col("o_custkey") % 10).alias("value"))
    return M.feature_gain(scores)


def _costs(spark) -> DataFrame:
    rows = [(q, s, float((q + 1) * (i + 1)), 10 * (i + 1)) for q in range(4) for i, s in enumerate(tree.STRATEGIES)]
    return spark.createDataFrame(rows, "qid long, strategy string, points_accessed double, elapsed_us long")


@query("mean_strategy_cost", "select 6.25::DOUBLE as mean_cost")
def mean_strategy_cost(spark, sf_dir):
    return M.mean_strategy_cost(_costs(spark))


@query("gain_over_mean", "select 2.5::DOUBLE as auto_cost, 6.25::DOUBLE as mean_cost, 1 - 2.5::DOUBLE / 6.25 as gain")
def gain_over_mean(spark, sf_dir):
    log = _costs(spark)
    return M.gain_over_mean(log, log.where("strategy = 'box_dfs'"))


@query("query_time", "select * from (values ('box_dfs', 10.0::DOUBLE, 4::BIGINT), ('box_bfs', 20.0, 4), ('ball_dfs', 30.0, 4), ('ball_bfs', 40.0, 4)) v(strategy, mean_us, queries)")
def query_time(spark, sf_dir):
    return M.query_time(_costs(spark))


@query("factor_ratios_fixture", "select avg(p_size) filter (where p_partkey % 4 in (1, 3)) / avg(p_size) filter (where p_partkey % 4 in (0, 2)) as bfs_over_dfs, avg(p_size) filter (where p_partkey % 4 in (0, 1)) / avg(p_size) filter (where p_partkey % 4 in (2, 3)) as box_over_ball from part")
def factor_ratios_fixture(spark, sf_dir):
    """Parts as a log: the key tells the strategy, the size the cost."""
    strategy = F.element_at(F.array(*[F.lit(s) for s in tree.STRATEGIES]), (F.col("p_partkey") % 4 + 1).cast("int"))
    return M.factor_ratio(table(spark, sf_dir, "part").select(strategy.alias("strategy"), F.col("p_size").alias("points_accessed")))


@query("prediction_share", "select 0.25::DOUBLE as share")
def prediction_share(spark, sf_dir):
    return spark.createDataFrame([(M.prediction_share(1.0, 4.0),)], "share double")


@query("path_metric_unequal", "select * from (values (0, 0), (1, -3), (2, 1)) v(i, w)")
def path_metric_unequal(spark, sf_dir):
    rows = [(0, [0, 1], [0, 1, 2, 0]), (1, [1], [0, 1, 2]), (2, [0, 1], [0, 1, 2])]
    return spark.createDataFrame(rows, "i int, a array<int>, b array<int>").select("i", selector.path_similarity(F.col("a"), F.col("b")).alias("w"))


@query("majority_ranking", "select * from (values (1::BIGINT, 2, 1), (1, 0, 2), (1, 1, 3), (1, 3, 4)) v(qid, strategy, place)")
def majority_ranking(spark, sf_dir):
    from pyspark.ml.functions import array_to_vector

    rows = spark.createDataFrame([(i, [0.0], y) for i, y in enumerate([2, 2, 2, 0, 0, 1])], "qid long, x array<double>, label int").select("qid", array_to_vector("x").alias("features"), "label")
    return selector.rank_strategies(selector.train_selector(rows, "majority"), rows.where("qid = 1").drop("label"))


@query("generated_queries", "select 50::BIGINT as n, true as from_points, true as k_in_range, true as r_in_range")
def generated_queries(spark, sf_dir):
    data = points(spark, sf_dir, "part2")
    k, r = selector.gen_knn_queries(data, 50, 5, 20), selector.gen_radius_queries(data, 50)
    reach = data.agg(F.sqrt(sum((F.max(F.element_at("coords", i)) - F.min(F.element_at("coords", i))) ** 2 for i in (1, 2))).alias("reach"))
    known = k.join(data, (F.col("pid") == F.col("qid")) & (F.col("coords") == F.col("qcoords"))).agg((F.count("*") == 50).alias("from_points"), (F.min("k").between(5, 20) & F.max("k").between(5, 20)).alias("k_in_range"))
    return k.agg(F.count("*").alias("n")).crossJoin(known).crossJoin(r.crossJoin(reach).agg(F.bool_and(F.col("r").between(0.001 * F.col("reach"), 0.05 * F.col("reach"))).alias("r_in_range")))


@query("split_80_10_10", "select true as whole, true as apart")
def split_80_10_10(spark, sf_dir):
    asked = _asked(points(spark, sf_dir, "ord2"), 1)
    parts = selector.split_80_10_10(asked)
    every = parts[0].select("qid").union(parts[1].select("qid")).union(parts[2].select("qid"))
    return every.agg(F.count("*").alias("n"), F.countDistinct("qid").alias("d")).crossJoin(asked.agg(F.count("*").alias("all"))).select((F.col("n") == F.col("all")).alias("whole"), (F.col("d") == F.col("n")).alias("apart"))


@query("cdf_sample_share", "select true as near_share, true as least_held")
def cdf_sample_share(spark, sf_dir):
    rows = table(spark, sf_dir, "lineitem").select(F.monotonically_increasing_id().alias("row"), F.xxhash64("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey").alias("pid"), (F.col("l_linenumber") % 3).alias("g"))
    share = cdf.cdf_sample(rows, 0.1).agg(F.count("*").alias("n")).crossJoin(rows.agg(F.count("*").alias("all")))
    held = cdf.cdf_sample(rows, 0.0001, keys=["g"], least=64).groupBy("g").agg(F.count("*").alias("n")).agg((F.min("n") >= 64).alias("least_held"))
    return share.select((F.abs(F.col("n") / F.col("all") - 0.1) < 0.03).alias("near_share")).crossJoin(held)


@query("cdf_tuned_submodels")
def cdf_tuned_submodels(spark, sf_dir):
    x = [r.x for r in points(spark, sf_dir, "ord2").select(F.element_at("coords", 1).alias("x"), F.xxhash64("pid").alias("h")).orderBy("h").limit(5000).collect()]
    return spark.createDataFrame([(l, e) for l, e in cdf.tune_submodels(x).items()], "l int, mean_error double")  # noqa: E741


@query("kmeans_indexed_base_tree", _KM)
def kmeans_indexed_base_tree(spark, sf_dir):
    out = kmeans.simplify(build_index(points(spark, sf_dir, "ord2"), mode="sort", t=4), 4, 3, "centroid_index")
    return out.select("cid", "n", F.round(F.element_at("coords", 1), 4).alias("c0"), F.round(F.element_at("coords", 2), 4).alias("c1"))


@query("kmeans_against_library", "select true as no_worse")
def kmeans_against_library(spark, sf_dir):
    data = points(spark, sf_dir, "ord2")
    own = kmeans.run(data, 4, 25)["history"][-1]["sse"]
    return spark.createDataFrame([(bool(own <= 1.25 * kmeans.mllib(data, 4, 25)),)], "no_worse boolean")


@query("spark_io")
def spark_io(spark, sf_dir):
    got = M.spark_io(spark, lambda: table(spark, sf_dir, "orders").groupBy("o_custkey").count().write.format("noop").mode("overwrite").save())
    return spark.createDataFrame([(k, int(v)) for k, v in got.items()], "metric string, value long")


# --- generic operators -------------------------------------------------------------------------------------------


@query("agg_mode", "select event_type from events group by 1 order by count(*) desc, 1 limit 1")
def agg_mode(spark, sf_dir):
    return table(spark, sf_dir, "events").agg(F.mode("event_type").alias("event_type"))


@query("agg_observed", "select count(*) as n, round(max(o_totalprice), 2) as most from orders")
def agg_observed(spark, sf_dir):
    seen = Observation()
    table(spark, sf_dir, "orders").observe(seen, F.count("*").alias("n"), F.max("o_totalprice").alias("most")).write.format("noop").mode("overwrite").save()
    return spark.createDataFrame([(seen.get["n"], round(float(seen.get["most"]), 2))], "n long, most double")


@query("agg_approx_distinct", "select true as near")
def agg_approx_distinct(spark, sf_dir):
    out = table(spark, sf_dir, "lineitem").agg(F.approx_count_distinct("l_partkey", 0.02).alias("a"), F.countDistinct("l_partkey").alias("e"))
    return out.select((F.abs(F.col("a") - F.col("e")) <= 0.1 * F.col("e")).alias("near"))


@query("agg_lists", "select n_regionkey, string_agg(n_name, ',' order by n_name) as names, count(*) as n from nation group by 1")
def agg_lists(spark, sf_dir):
    return table(spark, sf_dir, "nation").groupBy("n_regionkey").agg(F.array_join(F.array_sort(F.array_agg("n_name")), ",").alias("names"), F.size(F.collect_set("n_name")).cast("long").alias("n"))


@query("set_intersect_all", "select c_nationkey as k, count(*) as n from (select c_nationkey from customer intersect all select s_nationkey from supplier) group by 1")
def set_intersect_all(spark, sf_dir):
    a, b = table(spark, sf_dir, "customer").select(F.col("c_nationkey").alias("k")), table(spark, sf_dir, "supplier").select(F.col("s_nationkey").alias("k"))
    return a.intersectAll(b).groupBy("k").agg(F.count("*").alias("n"))


@query("join_full_outer", "select coalesce(a.k, b.k) as k, coalesce(a.n, 0) as customers, coalesce(b.n, 0) as suppliers from (select c_nationkey as k, count(*) as n from customer where c_acctbal < 0 group by 1) a full outer join (select s_nationkey as k, count(*) as n from supplier group by 1) b on a.k = b.k")
def join_full_outer(spark, sf_dir):
    a = table(spark, sf_dir, "customer").where("c_acctbal < 0").groupBy(F.col("c_nationkey").alias("k")).agg(F.count("*").alias("customers"))
    b = table(spark, sf_dir, "supplier").groupBy(F.col("s_nationkey").alias("k")).agg(F.count("*").alias("suppliers"))
    return a.join(b, "k", "full_outer").na.fill(0, ["customers", "suppliers"])


for _hint in ("merge", "shuffle_hash", "broadcast"):

    @query(f"join_hint_{_hint}", "select o_orderstatus, count(*) as n, round(sum(c_acctbal), 2) as total from orders join customer on o_custkey = c_custkey group by 1")
    def join_hint(spark, sf_dir, hint=_hint):
        out = table(spark, sf_dir, "orders").join(table(spark, sf_dir, "customer").hint(hint), F.col("o_custkey") == F.col("c_custkey"))
        return out.groupBy("o_orderstatus").agg(F.count("*").alias("n"), F.round(F.sum("c_acctbal"), 2).alias("total"))


@query("filter_predicates", "select count(*) as n from part where p_retailprice between 1000 and 1500 and p_size in (1, 5, 9, 13) and p_type is not null and p_type like '%A%' and regexp_matches(p_brand, '[0-9]$')")
def filter_predicates(spark, sf_dir):
    p = table(spark, sf_dir, "part")
    test = p.p_retailprice.between(1000, 1500) & p.p_size.isin(1, 5, 9, 13) & p.p_type.isNotNull() & p.p_type.like("%A%") & p.p_brand.rlike("[0-9]$")
    return relational.filter_points(p, test).agg(F.count("*").alias("n"))


@query("fn_json_write", """select c_custkey, '{"key":' || c_custkey || ',"nation":' || c_nationkey || '}' as json, c_nationkey as back from customer""")
def fn_json_write(spark, sf_dir):
    out = table(spark, sf_dir, "customer").select("c_custkey", F.to_json(F.struct(F.col("c_custkey").alias("key"), F.col("c_nationkey").alias("nation"))).alias("json"))
    return out.withColumn("back", F.from_json("json", "key long, nation int")["nation"])


@query("fn_variant", "select event_id, cast(props->>'$.k' as integer) as k from events")
def fn_variant(spark, sf_dir):
    return table(spark, sf_dir, "events").select("event_id", F.variant_get(F.parse_json("props"), "$.k", "int").alias("k"))


@query("fn_strings", "select n_nationkey, upper(n_name) as up, length(n_name) as len, substr(n_name, 1, 3) as head, n_name || '-' || n_regionkey as joined, replace(n_name, 'A', '*') as masked from nation")
def fn_strings(spark, sf_dir):
    n = F.col("n_name")
    return table(spark, sf_dir, "nation").select("n_nationkey", F.upper(n).alias("up"), F.length(n).cast("long").alias("len"), F.substring(n, 1, 3).alias("head"), F.concat_ws("-", n, F.col("n_regionkey").cast("string")).alias("joined"), F.replace(n, F.lit("A"), F.lit("*")).alias("masked"))


@query("fn_maps", "select r_regionkey, count(*) as n, max(n_nationkey) as top from nation join region on n_regionkey = r_regionkey group by 1")
def fn_maps(spark, sf_dir):
    held = table(spark, sf_dir, "nation").groupBy(F.col("n_regionkey").alias("r_regionkey")).agg(F.map_from_entries(F.collect_list(F.struct("n_nationkey", "n_name"))).alias("m"))
    return held.select("r_regionkey", F.size("m").cast("long").alias("n"), F.array_max(F.map_keys("m")).alias("top"))


@query("sort_global", "select o_orderkey, row_number() over (order by o_totalprice, o_orderkey) as place from orders")
def sort_global(spark, sf_dir):
    """A global sort by range exchange; places are a partition's rows before it and the row's place inside."""
    rows = table(spark, sf_dir, "orders").select("o_orderkey", "o_totalprice")
    return relational.global_places(rows, ["o_totalprice", "o_orderkey"]).select("o_orderkey", "place")


@query("sort_in_partitions", "select count(*) as n, 0::BIGINT as out_of_order from events")
def sort_in_partitions(spark, sf_dir):
    from pyspark.sql import Window

    rows = store.layout_by_cell(table(spark, sf_dir, "events").select(F.floor(F.col("value") / 10).alias("cell_id"), F.col("event_id").alias("leaf_id"), F.spark_partition_id().alias("before")))
    rows = rows.withColumn("part", F.spark_partition_id()).withColumn("at", F.monotonically_increasing_id())
    last = F.lag(F.struct("cell_id", "leaf_id")).over(Window.partitionBy("part").orderBy("at"))
    return rows.select((last > F.struct("cell_id", "leaf_id")).alias("wrong")).agg(F.count("*").alias("n"), F.count_if("wrong").alias("out_of_order"))


@query("dedupe_replicated", f"with p as ({SQL_VIEW['cus2'][1]}) select a.pid as a, b.pid as b from p as a, p as b where a.pid < b.pid and {_sq('a', 'b', 2)} <= 5.0")
def dedupe_replicated(spark, sf_dir):
    return relational.replicated_pairs(points(spark, sf_dir, "cus2"), 5.0)


@query("files_round_trip", "select 'csv' as format, count(*) as n, round(sum(c_acctbal), 2) as total from customer union all select 'json', count(*), round(sum(c_acctbal), 2) from customer union all select 'orc', count(*), round(sum(c_acctbal), 2) from customer")
def files_round_trip(spark, sf_dir):
    rows, out = table(spark, sf_dir, "customer").select("c_custkey", F.col("c_acctbal").cast("double").alias("c_acctbal")), None
    for kind in ("csv", "json", "orc"):
        path = f"{shared_dir(spark)}/files-{uuid.uuid4().hex}"
        rows.write.format(kind).save(path)
        got = spark.read.format(kind).schema("c_custkey long, c_acctbal double").load(path).agg(F.lit(kind).alias("format"), F.count("*").alias("n"), F.round(F.sum("c_acctbal"), 2).alias("total"))
        out = got if out is None else out.unionByName(got)
    return out


# --- streams -----------------------------------------------------------------------------------------------------

@query("stream_session_live", ORACLES["stream_session"])
def stream_session_live(spark, sf_dir):
    return _streamed(spark, sf_dir, ingest.sessions, "complete")


@query("stream_running_cells", "select cast(floor(value / 25.0) as bigint) as cell, count(*) as n from events group by 1")
def stream_running_cells(spark, sf_dir):
    return _streamed(spark, sf_dir, lambda e: ingest.cell_counts(e, 25.0), "complete")


@query("stream_stream_join", "select a.event_id as a_id, b.event_id as b_id from events a, events b where a.user_id = b.user_id and a.event_type = 'click' and b.event_type = 'purchase' and b.ts > a.ts and b.ts <= a.ts + interval '12 hours'")
def stream_stream_join(spark, sf_dir):
    folder = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    write_by_time(table(spark, sf_dir, "events"), folder, 4)
    side = lambda kind: ingest.events_stream(spark, folder, 4).where(F.col("event_type") == kind)
    return ingest.run_to_table(ingest.interval_pairs(side("click"), side("purchase"), "12 hours", "12 hours"), f"t{uuid.uuid4().hex}", "append", f"{folder}-checkpoint")


@query("stream_knn_answers", knn_sql("evt2", 100, 10))
def stream_knn_answers(spark, sf_dir):
    data = points(spark, sf_dir, "evt2")
    folder, out = (f"{shared_dir(spark)}/{n}-{uuid.uuid4().hex}" for n in ("asked", "answers"))
    _asked(data, 100).select("qid", "qcoords", "k").repartition(3).write.parquet(folder)
    asked = spark.readStream.schema("qid long, qcoords array<double>, k long").option("maxFilesPerTrigger", 1).parquet(folder)
    holder = ingest.IndexHolder(build_index(data))
    ingest.stream_knn(asked, holder, lambda rows, i: rows.write.mode("overwrite").parquet(f"{out}/batch={i}"), f"{folder}-checkpoint").awaitTermination()
    return _shown(spark.read.parquet(out))


@query("stream_restarted_knn", knn_sql("evt2", 100, 10))
def stream_restarted_knn(spark, sf_dir):
    """A batch that comes again after a restart changes nothing: what was taken is in the store's manifest."""
    data, path = points(spark, sf_dir, "evt2"), f"{shared_dir(spark)}/store-{uuid.uuid4().hex}"
    holder = ingest.IndexHolder(build_index(data.where("pid % 3 = 0"), t=4), path=path)
    holder.take(data.where("pid % 3 = 1"), 0)
    again = ingest.IndexHolder.reopened(spark, path)
    again.take(data.where("pid % 3 = 1"), 0)
    again.take(data.where("pid % 3 = 2"), 1)
    return _shown(search.knn(again.ix, _asked(data, 100)))


@query("grid_radius_wide", radius_sql("evt2", 100, 25.0))
def grid_radius_wide(spark, sf_dir):
    from pivotgrove.baselines import trees as B

    data = points(spark, sf_dir, "evt2")
    return B.grid_radius(data, _asked(data, 100, r=25.0), [20.0, 20.0])
