"""One query for each method, variant, baseline, measure and operator, and SQL for those that SQL can express."""

from __future__ import annotations

import uuid
from collections.abc import Callable
from functools import partial

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from pivotgrove import metrics as M
from pivotgrove import workloads
from pivotgrove.baselines import brute
from pivotgrove.baselines import trees as B
from pivotgrove.functions import geometry as G
from pivotgrove.operators import insertion, kmeans, levels, relational, search, selector, tree
from pivotgrove.operators.index import build_index
from pivotgrove.plans import cdf, fanout
from pivotgrove.runtime import shared_dir
from pivotgrove.sources import store
from pivotgrove.sources.points import days, extent, hours, melt, points, scaled, table, unmelt, validate
from pivotgrove.streaming import ingest

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return add


# --- SQL of the point views --------------------------------------------------------------------------------------

_DAY, _HOUR = "86400000000::DOUBLE", "3600000000::DOUBLE"
SQL_VIEW = {
    "ord2": (2, f"select o_orderkey as pid, o_totalprice as x0, epoch_us(o_orderdate)::DOUBLE / {_DAY} as x1 from orders"),
    "evt2": (2, f"select event_id as pid, value as x0, epoch_us(ts)::DOUBLE / {_HOUR} as x1 from events"),
    "evt3": (3, f"select event_id as pid, value as x0, epoch_us(ts)::DOUBLE / {_HOUR} as x1, user_id::DOUBLE as x2 from events"),
    "evt4": (4, f"select event_id as pid, value as x0, epoch_us(ts)::DOUBLE / {_HOUR} as x1, user_id::DOUBLE as x2, (props->>'$.k')::DOUBLE as x3 from events"),
    "part2": (2, "select p_partkey as pid, p_retailprice as x0, p_size::DOUBLE as x1 from part"),
    "cus2": (2, "select c_custkey as pid, c_acctbal as x0, c_nationkey::DOUBLE as x1 from customer"),
    "emb3": (3, "select vec_id as pid, embedding[1]::DOUBLE as x0, embedding[2]::DOUBLE as x1, embedding[3]::DOUBLE as x2 from embeddings"),
    "emb64": (64, "select vec_id as pid, " + ", ".join(f"embedding[{i + 1}]::DOUBLE as x{i}" for i in range(64)) + " from embeddings"),
}


def _sq(a: str, b: str, d: int) -> str:
    return "sqrt(" + " + ".join(f"({a}.x{i} - {b}.x{i}) * ({a}.x{i} - {b}.x{i})" for i in range(d)) + ")"


def knn_sql(view: str, mod: int, k: int, digits: int | None = None, more: str = "") -> str:
    d, sql = SQL_VIEW[view]
    shown = "dist" if digits is None else f"round(dist, {digits})"
    return f"with p as ({sql}), pairs as (select q.pid as qid, p.pid as pid, {_sq('p', 'q', d)} as dist from p, p as q where q.pid % {mod} = 0{more}), ranked as (select *, row_number() over (partition by qid order by dist, pid) as n from pairs) select qid, pid, cast(n as integer) as rank, {shown} as dist from ranked where n <= {k}"


def radius_sql(view: str, mod: int, r: float) -> str:
    d, sql = SQL_VIEW[view]
    return f"with p as ({sql}), pairs as (select q.pid as qid, p.pid as pid, {_sq('p', 'q', d)} as dist from p, p as q where q.pid % {mod} = 0) select qid, pid, dist from pairs where dist <= {r!r}::DOUBLE"


def _asked(data: DataFrame, mod: int, k: int = 10, r: float = 0.0) -> DataFrame:
    """The query set: every point whose id is divisible by mod."""
    return data.where(F.col("pid") % mod == 0).select(F.col("pid").alias("qid"), F.col("coords").alias("qcoords"), F.lit(k).cast("long").alias("k"), F.lit(float(r)).alias("r"))


def _shown(df: DataFrame, digits: int | None = None) -> DataFrame:
    return df.select("qid", "pid", F.col("rank").cast("int").alias("rank"), (F.col("dist") if digits is None else F.round("dist", digits)).alias("dist"))


def _flat(df: DataFrame, d: int) -> DataFrame:
    return df.select("pid", *[F.element_at("coords", i + 1).alias(f"x{i}") for i in range(d)])


# --- geometry ----------------------------------------------------------------------------------------------------

_Q = "[50000.0, 9000.0]"


@query("geo_dist_orders", f"with p as ({SQL_VIEW['ord2'][1]}) select pid, sqrt((x0 - 50000.0::DOUBLE) * (x0 - 50000.0::DOUBLE) + (x1 - 9000.0::DOUBLE) * (x1 - 9000.0::DOUBLE)) as dist from p")
def geo_dist_orders(spark, sf_dir):
    flat = _flat(points(spark, sf_dir, "ord2"), 2)
    return flat.select("pid", G.flat_dist([F.col("x0"), F.col("x1")], [F.lit(50000.0), F.lit(9000.0)]).alias("dist"))


_BOXES = f"with p as ({SQL_VIEW['evt2'][1]}), g as (select pid % 50 as grp, x0, x1 from p), b as (select grp, min(x0) as l0, max(x0) as h0, min(x1) as l1, max(x1) as h1, avg(x0) as c0, avg(x1) as c1, count(*) as n from g group by grp)"
_LOW = "sqrt(greatest(l0 - 600.0::DOUBLE, 600.0::DOUBLE - h0, 0) * greatest(l0 - 600.0::DOUBLE, 600.0::DOUBLE - h0, 0) + greatest(l1 - 1000000.0::DOUBLE, 1000000.0::DOUBLE - h1, 0) * greatest(l1 - 1000000.0::DOUBLE, 1000000.0::DOUBLE - h1, 0))"
_HIGH = "sqrt(greatest(abs(600.0::DOUBLE - l0), abs(600.0::DOUBLE - h0)) * greatest(abs(600.0::DOUBLE - l0), abs(600.0::DOUBLE - h0)) + greatest(abs(1000000.0::DOUBLE - l1), abs(1000000.0::DOUBLE - h1)) * greatest(abs(1000000.0::DOUBLE - l1), abs(1000000.0::DOUBLE - h1)))"


def _groups(spark, sf_dir):
    return points(spark, sf_dir, "evt2").withColumn("grp", F.col("pid") % 50)


@query("geo_box_bounds", f"{_BOXES} select grp, {_LOW} as low, {_HIGH} as high, {_LOW} > 400000.0 as pruned from b")
def geo_box_bounds(spark, sf_dir):
    q = F.array(F.lit(600.0), F.lit(1000000.0))
    b = G.mbr(_groups(spark, sf_dir), ["grp"], 2)
    return b.select("grp", G.box_lower_bound(F.col("lo"), F.col("hi"), q).alias("low"), G.box_upper_bound(F.col("lo"), F.col("hi"), q).alias("high"), G.box_prunes(F.col("lo"), F.col("hi"), q, F.lit(400000.0)).alias("pruned"))


_BALL = f"{_BOXES}, r as (select g.grp, max(sqrt((x0 - c0) * (x0 - c0) + (x1 - c1) * (x1 - c1))) as rad from g join b using (grp) group by g.grp)"
_CD = "sqrt((c0 - 600.0::DOUBLE) * (c0 - 600.0::DOUBLE) + (c1 - 1000000.0::DOUBLE) * (c1 - 1000000.0::DOUBLE))"


@query("geo_ball_bounds", f"{_BALL} select grp, round(greatest({_CD} - rad, 0), 4) as low, round({_CD} + rad, 4) as high, {_CD} > rad + 1000.0 as pruned from b join r using (grp)")
def geo_ball_bounds(spark, sf_dir):
    q = F.array(F.lit(600.0), F.lit(1000000.0))
    b = G.mbb(_groups(spark, sf_dir), ["grp"], 2)
    return b.select("grp", F.round(G.ball_lower_bound(F.col("center"), F.col("radius"), q), 4).alias("low"), F.round(G.ball_upper_bound(F.col("center"), F.col("radius"), q), 4).alias("high"), G.ball_prunes(F.col("center"), F.col("radius"), q, F.lit(1000.0)).alias("pruned"))


@query("geo_box_overlap", f"{_BOXES} select grp, l0 <= 2.0 and h0 >= 1.0 and l1 <= 2000000.0 and h1 >= 0.0 as overlaps from b")
def geo_box_overlap(spark, sf_dir):
    b = G.mbr(_groups(spark, sf_dir), ["grp"], 2)
    lo, hi = G.query_box(F.array(F.lit(1.5), F.lit(1000000.0)), F.lit(0.5))
    box = b.select("grp", "lo", "hi", F.array(F.element_at(lo, 1), F.lit(0.0)).alias("qlo"), F.array(F.element_at(hi, 1), F.lit(2000000.0)).alias("qhi"))
    return box.select("grp", G.boxes_overlap(F.col("lo"), F.col("hi"), F.col("qlo"), F.col("qhi")).alias("overlaps"))


@query("geo_sql_functions", f"with p as ({SQL_VIEW['ord2'][1]}) select pid, greatest(sqrt((0.0::DOUBLE - x0) * (0.0::DOUBLE - x0) + (0.0::DOUBLE - x1) * (0.0::DOUBLE - x1)) - 5.0::DOUBLE, 0.0) as low from p")
def geo_sql_functions(spark, sf_dir):
    G.register_sql(spark)
    return points(spark, sf_dir, "ord2").selectExpr("pid", "ball_lower_bound(array(0D, 0D), 5D, coords) as low")


@query("geo_ball_merge", f"{_BALL}, w as (select grp % 5 as parent, b.n, c0, c1, rad from b join r using (grp)), m as (select parent, sum(c0 * n) / sum(n) as m0, sum(c1 * n) / sum(n) as m1, cast(sum(n) as bigint) as n from w group by parent) select parent, round(any_value(m0), 4) as c0, round(any_value(m1), 3) as c1, round(max(sqrt((c0 - m0) * (c0 - m0) + (c1 - m1) * (c1 - m1)) + rad), 3) as radius, any_value(m.n) as n_points from w join m using (parent) group by parent")
def geo_ball_merge(spark, sf_dir):
    balls = G.mbb(_groups(spark, sf_dir), ["grp"], 2).withColumn("parent", F.col("grp") % 5)
    out = G.mbb_merge(balls, ["parent"], 2)
    return out.select("parent", F.round(F.element_at("center", 1), 4).alias("c0"), F.round(F.element_at("center", 2), 3).alias("c1"), F.round("radius", 3).alias("radius"), "n_points")


# --- fan-out -----------------------------------------------------------------------------------------------------

#: The points are those of orders, told by their keys.
_FAN = "with z as (select count(distinct o_orderkey)::DOUBLE as n from orders), r as (select cast(range as integer) as t, n from range(2, 11), z), l as (select t, n, (select cast(count(*) as integer) from range(0, 65) as g(i) where 30.0 * pow(t::DOUBLE, i::DOUBLE) < n) as levels from r), s as (select *, n / pow(t::DOUBLE, levels::DOUBLE) as share from l), c as (select *, cast(case when share - floor(share) > 0.5 then ceil(share) else floor(share) end as bigint) as c0, t * t / 2.0::DOUBLE + t / 2.0::DOUBLE - 1.0::DOUBLE as cost from s)"


def _orders(spark, sf_dir) -> int:
    return table(spark, sf_dir, "orders").agg(F.countDistinct("o_orderkey")).first()[0]


@query("fanout_table", f"{_FAN} select t, levels, c0, round(log10(pow(c0 * cost, levels::DOUBLE)), 9) as log_printed, round(levels * cost / t, 9) as level_sum from c")
def fanout_table(spark, sf_dir):
    out = fanout.fanout_table(spark, _orders(spark, sf_dir), 30)
    return out.select("t", "levels", "c0", F.round(F.log10("printed"), 9).alias("log_printed"), F.round("level_sum", 9).alias("level_sum"))


@query("fanout_best", f"{_FAN} select min_by(t, pow(c0 * cost, levels::DOUBLE)) as best_t from c")
def fanout_best(spark, sf_dir):
    return fanout.fanout_table(spark, _orders(spark, sf_dir), 30).agg(F.min_by("t", "printed").alias("best_t"))


@query("fanout_solvers", f"{_FAN}, b as (select min_by(t, pow(c0 * cost, levels::DOUBLE)) as t from c where c0 >= 1 and t <= greatest(2, ceil(n / 30))) select 'anneal' as method, t from b union all select 'scan', t from b")
def fanout_solvers(spark, sf_dir):
    n = _orders(spark, sf_dir)
    rows = [(m, fanout.optimal_fanout(n, 30, method=m, seed=3)) for m in ("anneal", "scan")]
    return spark.createDataFrame(rows, "method string, t int")


_SIZES = "with recursive g as (select distinct count(*)::BIGINT as n from orders group by o_custkey), k as (select n, t::INTEGER as t from g, range(2, 5) r(t)), w(n, t, m, c) as (select n, t, n, 0::BIGINT from k union all select n, t, ((i + 1) * m) // t - (i * m) // t, (((i + 1) * m) // t - (i * m) // t) * least(i + 1, t - 1) from w, range(0, 4) x(i) where m > 3 and i < t), e as (select n, t, sum(c) / n::DOUBLE as recursive from w group by n, t), l as (select *, (select count(*) from range(0, 65) y(j) where 3.0 * pow(t::DOUBLE, j::DOUBLE) < n) as levels from e), s as (select *, n / pow(t::DOUBLE, levels::DOUBLE) as share from l)"


@query("fanout_example8", f"{_SIZES} select n, t, round(pow(case when share - floor(share) > 0.5 then ceil(share) else floor(share) end * (t * t / 2.0::DOUBLE + t / 2.0::DOUBLE - 1), levels::DOUBLE) / n, 9) as per_point, round(recursive, 9) as recursive from s")
def fanout_example8(spark, sf_dir):
    """The worked example (eight points, three a leaf) for every number of orders that a customer has."""
    sizes = [r.n for r in table(spark, sf_dir, "orders").groupBy("o_custkey").agg(F.count("*").alias("n")).select("n").distinct().collect()]
    rows = [(n, t, fanout.aepl_printed_per_point(n, 3, t), fanout.aepl_recursive(n, 3, t)) for n in sizes for t in (2, 3, 4)]
    return spark.createDataFrame(rows, "n long, t int, per_point double, recursive double").select("n", "t", F.round("per_point", 9).alias("per_point"), F.round("recursive", 9).alias("recursive"))


# --- trees by level ----------------------------------------------------------------------------------------------


def tree_sql(view: str, t: int, c: int, depth: int) -> str:
    d, sql = SQL_VIEW[view]
    out = f"with a0 as (select *, 0::BIGINT as node from ({sql}))"
    for i in range(depth):
        out += f", b{i} as (select *, row_number() over (partition by node order by x{i % d}, pid) - 1 as r, count(*) over (partition by node) as m from a{i}), a{i + 1} as (select * exclude (node, r, m), cast(node * {t} + case when m <= {c} then 0 else floor(r * {t} / m::DOUBLE) end as bigint) as node from b{i})"
    return out


@query("tree_exact_t3_assign", tree_sql("ord2", 3, 30, 4) + " select pid, node from a4")
def tree_exact_t3_assign(spark, sf_dir):
    return levels.assign_exact(points(spark, sf_dir, "ord2"), 3, 30, 4, 2).select("pid", "node")


@query("tree_exact_t2_leafsizes", tree_sql("evt2", 2, 30, 6) + " select node, count(*) as n from a6 group by node")
def tree_exact_t2_leafsizes(spark, sf_dir):
    return levels.assign_exact(points(spark, sf_dir, "evt2"), 2, 30, 6, 2).groupBy("node").agg(F.count("*").alias("n"))


def _width_sql() -> str:
    out = f"with a0 as (select *, 0::BIGINT as node from ({SQL_VIEW['evt2'][1]}))"
    for i in range(3):
        out += f", b{i} as (select *, min(x{i % 2}) over (partition by node) as a, max(x{i % 2}) over (partition by node) as b from a{i}), a{i + 1} as (select * exclude (node, a, b), cast(node * 4 + case when a = b then 0 else least(3, floor((x{i % 2} - a) * 4 / (b - a))) end as bigint) as node from b{i})"
    return out + " select node, count(*) as n from a3 group by node"


@query("tree_equal_width", _width_sql())
def tree_equal_width(spark, sf_dir):
    return levels.assign_equal_width(points(spark, sf_dir, "evt2"), 4, 3, 2).groupBy("node").agg(F.count("*").alias("n"))


@query("mbr_by_leaf", tree_sql("ord2", 3, 30, 3) + " select node, min(x0) as l0, max(x0) as h0, min(x1) as l1, max(x1) as h1, count(*) as n from a3 group by node")
def mbr_by_leaf(spark, sf_dir):
    b = G.mbr(levels.assign_exact(points(spark, sf_dir, "ord2"), 3, 30, 3, 2), ["node"], 2)
    at = lambda c, i, n: F.element_at(c, i).alias(n)
    return b.select("node", at("lo", 1, "l0"), at("hi", 1, "h0"), at("lo", 2, "l1"), at("hi", 2, "h1"), F.col("n_points").alias("n"))


@query("mbb_by_leaf", tree_sql("ord2", 3, 30, 2) + ", c as (select node, avg(x0) as c0, avg(x1) as c1 from a2 group by node) select node, round(any_value(c0), 4) as c0, round(any_value(c1), 4) as c1, round(max(sqrt((x0 - c0) * (x0 - c0) + (x1 - c1) * (x1 - c1))), 4) as radius from a2 join c using (node) group by node")
def mbb_by_leaf(spark, sf_dir):
    b = G.mbb(levels.assign_exact(points(spark, sf_dir, "ord2"), 3, 30, 2, 2), ["node"], 2)
    return b.select("node", F.round(F.element_at("center", 1), 4).alias("c0"), F.round(F.element_at("center", 2), 4).alias("c1"), F.round("radius", 4).alias("radius"))


@query("aepl_exact_tree", tree_sql("ord2", 3, 1, 4) + " select round(avg(least((node // 27) % 3 + 1, 2) + least((node // 9) % 3 + 1, 2) + least((node // 3) % 3 + 1, 2) + least(node % 3 + 1, 2)), 9) as aepl from a4")
def aepl_exact_tree(spark, sf_dir):
    out = levels.exact_aepl(levels.assign_exact(points(spark, sf_dir, "ord2"), 3, 1, 4, 2), 3, 4)
    return out.select(F.round("aepl", 9).alias("aepl"))


# --- pivots and distribution functions ---------------------------------------------------------------------------


def _disc_sql(column: str, source: str, t: int) -> str:
    return " union all ".join(f"select {i} as i, quantile_disc({column}, {i / t!r}) as pivot from {source}" for i in range(1, t))


@query("pivots_exact_t4", _disc_sql("l_extendedprice", "lineitem", 4))
def pivots_exact_t4(spark, sf_dir):
    return levels.exact_pivots(points(spark, sf_dir, "li2"), 4, 0)


@query("pivots_disc", _disc_sql("o_totalprice", "orders", 8))
def pivots_disc(spark, sf_dir):
    return levels.exact_pivots(points(spark, sf_dir, "ord2"), 8, 0)


@query("pivots_sketch")
def pivots_sketch(spark, sf_dir):
    return levels.sketch_pivots(points(spark, sf_dir, "li2"), 8, 0)


L = 20


def _sample(spark, sf_dir):
    return table(spark, sf_dir, "orders").where("o_orderkey % 10 = 0").select(F.col("o_orderkey").alias("pid"), F.col("o_totalprice").alias("x"), F.lit(0).alias("g"))


def _models(spark, sf_dir, kappa: bool = False):
    ecdf = cdf.empirical_cdf(_sample(spark, sf_dir), ["g"], "x")
    roots = cdf.fit_root(ecdf, ["g"], "x", L)
    return ecdf, roots, cdf.fit_sub_plf(ecdf, roots, ["g"], "x", L)


_ECDF = "with s as (select o_orderkey as pid, o_totalprice as x from orders where o_orderkey % 10 = 0), e as (select pid, x, (row_number() over (order by x, pid) - 1)::DOUBLE / count(*) over () as f from s)"
_ROOT = f"{_ECDF}, m as (select count(*) as n, sum(x) as sx, sum(x * x) as sxx, sum(f * {L}) as su, sum(x * f * {L}) as sxu from e), rt as (select n, (n * sxu - sx * su) / (n * sxx - sx * sx) as alpha, (su - (n * sxu - sx * su) / (n * sxx - sx * sx) * sx) / n as beta from m)"
_SUBS = f"{_ROOT}, u as (select e.*, cast(greatest(0, least({L - 1}, floor(alpha * x + beta))) as integer) as u from e, rt), sub as (select u, min(x) as xlo, max(x) as xhi, min(f) as flo, max(f) as fhi, count(*) as n from u group by u)"
_PRED = f"{_SUBS}, w as (select o_orderkey as pid, o_totalprice as x, cast(greatest(0, least({L - 1}, floor(alpha * o_totalprice + beta))) as integer) as u from orders, rt), pr as (select pid, x, flo + case when xhi > xlo then greatest(0.0, least(1.0, (x - xlo) / (xhi - xlo))) else 0.5 end * (fhi - flo) as predicted from w left join sub using (u))"


@query("ecdf_sample", f"{_ECDF} select pid, f from e")
def ecdf_sample(spark, sf_dir):
    return cdf.empirical_cdf(_sample(spark, sf_dir), ["g"], "x").select("pid", "f")


@query("ecdf_variants", _ECDF + " select pid, percent_rank() over (order by x) as p, cume_dist() over (order by x) as c from s")
def ecdf_variants(spark, sf_dir):
    s = _sample(spark, sf_dir)
    a = cdf.empirical_cdf(s, ["g"], "x", kind="percent_rank").withColumnRenamed("f", "p")
    return cdf.empirical_cdf(a, ["g"], "x", kind="cume_dist").select("pid", "p", F.col("f").alias("c"))


@query("cdf_root_fit", f"{_ROOT} select n, round(alpha, 9) as alpha, round(beta, 6) as beta from rt")
def cdf_root_fit(spark, sf_dir):
    return _models(spark, sf_dir)[1].select("n", F.round("alpha", 9).alias("alpha"), F.round("beta", 6).alias("beta"))


@query("cdf_sub_plf", f"{_SUBS} select u, xlo, xhi, flo, fhi, n from sub")
def cdf_sub_plf(spark, sf_dir):
    return _models(spark, sf_dir)[2].select("u", "xlo", "xhi", "flo", "fhi", "n")


@query("cdf_sub_lsq", f"{_SUBS} select u, round(regr_slope(f, x) * 1e6, 4) as slope, round(regr_intercept(f, x), 4) as intercept from u group by u having count(*) > 2")
def cdf_sub_lsq(spark, sf_dir):
    ecdf, roots, _ = _models(spark, sf_dir)
    return cdf.fit_sub_lsq(ecdf, roots, ["g"], "x", L).where("n > 2").select("u", F.round(F.col("slope") * 1e6, 4).alias("slope"), F.round("intercept", 4).alias("intercept"))


def _predicted(spark, sf_dir, filled: bool = False):
    _, roots, subs = _models(spark, sf_dir)
    subs = cdf.fill_subs(subs, ["g"], L) if filled else subs
    rows = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("pid"), F.col("o_totalprice").alias("x"), F.lit(0).alias("g"))
    return cdf.predict_cdf(rows, roots, subs, ["g"], "x", L)


@query("cdf_predict", f"{_PRED} select pid, round(predicted, 9) as predicted from pr")
def cdf_predict(spark, sf_dir):
    return _predicted(spark, sf_dir).select("pid", F.round("predicted", 9).alias("predicted"))


@query("cdf_error", f"{_PRED}, t as (select predicted, (row_number() over (order by x, pid) - 1)::DOUBLE / count(*) over () as f from pr where predicted is not null) select round(max(abs(predicted - f)), 8) as max_error, round(avg(abs(predicted - f)), 8) as mean_error, count(*) as n from t")
def cdf_error(spark, sf_dir):
    return cdf.cdf_error(_predicted(spark, sf_dir), "x").select(F.round("max_error", 8).alias("max_error"), F.round("mean_error", 8).alias("mean_error"), "n")


@query("pivots_candidate_median", f"{_PRED}, q as (select cast(range as integer) as i, range / 4.0::DOUBLE as q from range(1, 4)) select i, median(x) as pivot, count(*) as candidates from pr, q where abs(predicted - q) <= 0.15 group by i")
def pivots_candidate_median(spark, sf_dir):
    return levels.candidate_median_pivots(_predicted(spark, sf_dir), "x", 4, 0.15)


@query("pivots_rank_corrected", _disc_sql("o_totalprice", "orders", 4))
def pivots_rank_corrected(spark, sf_dir):
    return levels.rank_corrected_pivots(_predicted(spark, sf_dir, True), "x", 4, 0.15)


@query("cdf_incremental_refit", "with f as (select event_id, value as x, event_id::DOUBLE / 1000 as u from events where event_id % 7 != 0) select count(*) as n, round(regr_slope(u, x), 9) as alpha, round(regr_intercept(u, x), 6) as beta from f")
def cdf_incremental_refit(spark, sf_dir):
    e = table(spark, sf_dir, "events").select(F.lit(0).alias("g"), "event_id", F.col("value").alias("x"), (F.col("event_id") / 1000).alias("f"))
    n = e.agg(F.max("event_id")).first()[0]
    sums = lambda d: cdf.root_sums(d, ["g"], "x", 1).select("g", "n", "sx", "sxx", "su", "sxu")
    base, come, gone = sums(e.where(F.col("event_id") < 0.8 * n)), sums(e.where(F.col("event_id") >= 0.8 * n)), sums(e.where("event_id % 7 = 0"))
    out = cdf.refit_root(base, come, gone, ["g"])
    return out.select("n", F.round("alpha", 9).alias("alpha"), F.round("beta", 6).alias("beta"))


# --- search ------------------------------------------------------------------------------------------------------


def _knn(view: str, mod: int, strategy: str, spark, sf_dir, digits: int | None = None, child_order: str = "nearest", home: bool = False, **options):
    data = points(spark, sf_dir, view)
    return _shown(search.knn(build_index(data, **options), _asked(data, mod), strategy, child_order, home), digits)


for _s in tree.STRATEGIES:
    query(f"knn_{_s}", knn_sql("ord2", 100, 10))(partial(_knn, "ord2", 100, _s))
    query(f"knn_events_{_s}", knn_sql("evt2", 100, 10))(partial(_knn, "evt2", 100, _s, cell_points=2500))
query("knn_nearest_first_home_pass", knn_sql("ord2", 100, 10))(partial(_knn, "ord2", 100, "box_dfs", home=True, cell_points=4000))
query("knn_pivot_order", knn_sql("ord2", 100, 10))(partial(_knn, "ord2", 100, "ball_dfs", child_order="pivot"))
query("knn_3d", knn_sql("evt3", 100, 10))(partial(_knn, "evt3", 100, "box_dfs"))
query("knn_4d", knn_sql("evt4", 100, 10))(partial(_knn, "evt4", 100, "ball_bfs"))
query("knn_ties", knn_sql("part2", 100, 10))(partial(_knn, "part2", 100, "box_bfs"))
query("knn_negative", knn_sql("cus2", 100, 10))(partial(_knn, "cus2", 100, "ball_dfs"))
query("knn_emb3", knn_sql("emb3", 100, 10))(partial(_knn, "emb3", 100, "ball_dfs"))
query("knn_emb64", knn_sql("emb64", 100, 5, 5))(lambda spark, sf_dir: _shown(search.knn(build_index(points(spark, sf_dir, "emb64")), _asked(points(spark, sf_dir, "emb64"), 100, 5), "box_dfs"), 5))
for _m in tree.MODES:
    query(f"knn_build_{_m}", knn_sql("ord2", 100, 10))(partial(_knn, "ord2", 100, "box_dfs", mode=_m))


def _radius(view: str, mod: int, r: float, strategy: str, spark, sf_dir, accept: bool = False):
    data = points(spark, sf_dir, view)
    return search.radius(build_index(data, cell_points=4000), _asked(data, mod, r=r), strategy, accept)


for _s in tree.STRATEGIES:
    query(f"radius_{_s}", radius_sql("ord2", 100, 800.0))(partial(_radius, "ord2", 100, 800.0, _s))
query("radius_accept_inside", radius_sql("evt2", 100, 60.0))(partial(_radius, "evt2", 100, 60.0, "ball_bfs", accept=True))


@query("radius_count", f"select qid, count(*) as n from ({radius_sql('evt3', 100, 20.0)}) group by qid")
def radius_count(spark, sf_dir):
    return _radius("evt3", 100, 20.0, "box_dfs", spark, sf_dir).groupBy("qid").agg(F.count("*").alias("n"))


@query("brute_knn", knn_sql("ord2", 100, 10))
def brute_knn(spark, sf_dir):
    data = points(spark, sf_dir, "ord2")
    return _shown(brute.knn(data, _asked(data, 100)))


@query("brute_radius", radius_sql("ord2", 100, 800.0))
def brute_radius(spark, sf_dir):
    data = points(spark, sf_dir, "ord2")
    return brute.radius(data, _asked(data, 100, r=800.0))


@query("knn_join_suppliers", "with pairs as (select s_suppkey as qid, c_custkey as pid, abs(s_acctbal - c_acctbal) as d0, s_nationkey - c_nationkey as d1 from supplier, customer), k as (select qid, pid, sqrt(d0 * d0 + (d1 * d1)::DOUBLE) as dist from pairs), r as (select *, row_number() over (partition by qid order by dist, pid) as n from k) select qid, pid, cast(n as integer) as rank, dist from r where n <= 3")
def knn_join_suppliers(spark, sf_dir):
    sup = table(spark, sf_dir, "supplier").select(F.col("s_suppkey").cast("long").alias("pid"), F.array(F.col("s_acctbal").cast("double"), F.col("s_nationkey").cast("double")).alias("coords"))
    return _shown(search.knn_join(build_index(points(spark, sf_dir, "cus2")), sup, 3))


@query("distance_join", f"with p as ({SQL_VIEW['cus2'][1]}) select a.pid as qid, b.pid as pid, {_sq('a', 'b', 2)} as dist from p as a, p as b where {_sq('a', 'b', 2)} <= 5.0")
def distance_join(spark, sf_dir):
    data = points(spark, sf_dir, "cus2")
    return search.distance_join(build_index(data), data, 5.0)


@query("access_counts")
def access_counts(spark, sf_dir):
    data = points(spark, sf_dir, "ord2")
    return M.points_accessed(search.access_log(build_index(data), _every(data, 100), timed=False), True)


def _every(data: DataFrame, mod: int) -> DataFrame:
    return _asked(data, mod, r=500.0).withColumn("strategy", F.explode(F.array(*[F.lit(s) for s in tree.STRATEGIES])))


@query("two_factor_ratios")
def two_factor_ratios(spark, sf_dir):
    data = points(spark, sf_dir, "ord2")
    return M.factor_ratio(search.access_log(build_index(data), _every(data, 100), timed=False))


@query("search_explained")
def search_explained(spark, sf_dir):
    data = points(spark, sf_dir, "ord2")
    return search.explain_search(build_index(data, cell_points=2000), _asked(data, 100)).drop("cells")


@query("index_shape")
def index_shape(spark, sf_dir):
    ix = build_index(points(spark, sf_dir, "ord2"))
    return M.tree_shape(ix).crossJoin(M.aepl(ix)).crossJoin(M.index_bytes(ix)).crossJoin(M.pivot_rank_error(points(spark, sf_dir, "ord2"), ix))


@query("index_exactness", "select 0::BIGINT as missing, 0::BIGINT as extra")
def index_exactness(spark, sf_dir):
    data = points(spark, sf_dir, "evt2")
    return M.exactness(_shown(search.knn(build_index(data, cell_points=1500), _asked(data, 100), "ball_bfs")), _shown(brute.knn(data, _asked(data, 100))))


@query("index_store_reopened", knn_sql("ord2", 100, 10))
def index_store_reopened(spark, sf_dir):
    data = points(spark, sf_dir, "ord2")
    path = f"{shared_dir(spark)}/store-{uuid.uuid4().hex}"
    store.save(build_index(data), path)
    return _shown(search.knn(store.load(spark, path, 0), _asked(data, 100)))


# --- insertion ---------------------------------------------------------------------------------------------------


def _grown(spark, sf_dir, rebuild: str = "selective", mode: str = "rank_corrected", cuts=(0.8, 0.81, 0.9, 1.0)):
    data = points(spark, sf_dir, "evt2")
    n = data.agg(F.max("pid")).first()[0] + 1
    ix = build_index(data.where(F.col("pid") < int(cuts[0] * n)), t=4, mode=mode, cell_points=4000)
    for a, b in zip(cuts, cuts[1:], strict=False):
        ix = insertion.insert_batch(ix, data.where((F.col("pid") >= int(a * n)) & (F.col("pid") < int(b * n))), rebuild)
    return data, ix


def _grown_knn(spark, sf_dir, **how):
    data, ix = _grown(spark, sf_dir, **how)
    return _shown(search.knn(ix, _asked(data, 100)))


query("insert_then_knn", knn_sql("evt2", 100, 10))(partial(_grown_knn, rebuild="none"))
query("rebuild_selective_knn", knn_sql("evt2", 100, 10))(_grown_knn)
query("rebuild_full_knn", knn_sql("evt2", 100, 10))(partial(_grown_knn, rebuild="full", mode="sort"))


@query("insert_route_counts", "select count(*) as n, cast(count(distinct event_id) as bigint) as ids from events")
def insert_route_counts(spark, sf_dir):
    data = points(spark, sf_dir, "evt2")
    ix = build_index(data.where("pid % 5 != 0"), cell_points=4000)
    return insertion.route_to_leaf(data, ix).agg(F.count("*").alias("n"), F.countDistinct("pid").alias("ids"))


@query("rebuild_cost")
def rebuild_cost(spark, sf_dir):
    return M.rebuild_fraction(insertion.rebuild_log(_grown(spark, sf_dir)[1], spark))


@query("balance_audit_index")
def balance_audit_index(spark, sf_dir):
    return insertion.audit_balance(_grown(spark, sf_dir, rebuild="none")[1].nodes(), 0.9).groupBy("cell_id").agg(F.count("*").alias("violations"))


_KIDS = "(values (1, 0, 6), (1, 1, 3), (1, 2, 9), (2, 0, 5), (2, 1, 5), (2, 2, 6)) k(node, ordinal, n)"
_KID_ROWS = [(1, 0, 6), (1, 1, 3), (1, 2, 9), (2, 0, 5), (2, 1, 5), (2, 2, 6)]


@query("balance_audit", "with k as (select p_size as node, cast((p_partkey % 7) // 3 as integer) as ordinal, count(*) as n from part group by 1, 2), t as (select node, sum(n) as total, count(*) as t from k group by node) select k.node, k.ordinal, k.n from k join t using (node) where t > 1 and k.n >= (case when 0.8 > (t - 1) / t::DOUBLE then 0.8::DOUBLE else (t - 1) / t::DOUBLE + (1 - (t - 1) / t::DOUBLE) / 2 end) / (t - 1) * total")
def balance_audit(spark, sf_dir):
    """Parts of each size under three children of unequal share."""
    kids = table(spark, sf_dir, "part").groupBy(F.col("p_size").alias("parent_id"), F.floor((F.col("p_partkey") % 7) / 3).cast("int").alias("ordinal")).agg(F.count("*").alias("n_points")).withColumn("cell_id", F.lit(0))
    return insertion.audit_balance(kids, 0.8).select(F.col("parent_id").alias("node"), "ordinal", F.col("n_points").alias("n"))


@query("rebuild_range_fixture", "select 1 as node, 1 as i0, 2 as i1, 12::BIGINT as zeta")
def rebuild_range_fixture(spark, sf_dir):
    kids = spark.createDataFrame(_KID_ROWS, "node int, ordinal int, n_points int")
    return insertion.choose_rebuild_range(kids, 0.8, ("node",)).select("node", "i0", "i1", "zeta")


@query("rebuild_points_saved", "select 12::BIGINT as rebuilt, 18::BIGINT as full, 12.0::DOUBLE / 18 as fraction, 1::BIGINT as rebuilds")
def rebuild_points_saved(spark, sf_dir):
    return M.rebuild_fraction(spark.createDataFrame([(12, 18)], "points_rebuilt long, points_full long"))


# --- strategy selection ------------------------------------------------------------------------------------------


@query("path_metric_fixture", "select * from (values (0, 1), (1, -3), (2, 3)) v(i, w)")
def path_metric_fixture(spark, sf_dir):
    rows = [(0, [0, 1, 0], [0, 1, 2]), (1, [0, 1, 0], [2, 1, 0]), (2, [0, 1, 0], [0, 1, 0])]
    return spark.createDataFrame(rows, "i int, a array<int>, b array<int>").select("i", selector.path_similarity(F.col("a"), F.col("b")).alias("w"))


_DIGITS = "case when (a.node // 9) = (b.node // 9) then case when a.node // 3 = b.node // 3 then case when a.node = b.node then 3 else 2 end else 1 end else 0 end"


@query("similarity_graph", tree_sql("ord2", 3, 1, 3) + f" select a.pid as src, b.pid as dst, 2 * ({_DIGITS}) - 3 as w from a3 as a, a3 as b where a.pid < b.pid and a.pid % 100 = 0 and b.pid % 100 = 0")
def similarity_graph(spark, sf_dir):
    assigned = levels.assign_exact(points(spark, sf_dir, "ord2"), 3, 1, 3, 2).where("pid % 100 = 0")
    path = F.array(*[(F.floor(F.col("node") / 3**i) % 3).cast("int") for i in (2, 1, 0)])
    return selector.similarity_graph(assigned.select("pid", path.alias("path")))


@query("features_f1", f"with p as ({SQL_VIEW['ord2'][1]}) select pid as qid, x0, x1, 10.0::DOUBLE as k from p where pid % 100 = 0")
def features_f1(spark, sf_dir):
    f1 = selector.features_f1(_asked(points(spark, sf_dir, "ord2"), 100).drop("r"))
    return f1.select("qid", *[F.element_at("f1", i + 1).alias(n) for i, n in enumerate(("x0", "x1", "k"))])


@query("features_f2")
def features_f2(spark, sf_dir):
    data = points(spark, sf_dir, "ord2")
    return selector.features_f2(build_index(data), _asked(data, 100))


@query("labels_by_work")
def labels_by_work(spark, sf_dir):
    data = points(spark, sf_dir, "ord2")
    return selector.label_queries(build_index(data), _asked(data, 100), child_order="pivot").select("qid", "label")


@query("labels_early_stop_differ", "select 0::BIGINT as differing")
def labels_early_stop_differ(spark, sf_dir):
    data = points(spark, sf_dir, "part2")
    ix, asked = build_index(data), _asked(data, 100)
    other = selector.label_early_stop(ix, asked).withColumnRenamed("label", "early")
    return selector.label_queries(ix, asked).join(other, "qid").agg(F.count_if(F.col("label") != F.col("early")).alias("differing"))


def _labelled(spark, sf_dir):
    data = points(spark, sf_dir, "ord2")
    ix = build_index(data)
    train = selector.gen_knn_queries(data, 80, 1, 50)
    rows = selector.features(ix, train, "f").join(selector.label_queries(ix, train, child_order="pivot"), "qid")
    return data, ix, selector.train_selector(rows.select("features", "label"), "tree")


@query("knn_auto", knn_sql("ord2", 100, 10))
def knn_auto(spark, sf_dir):
    data, ix, model = _labelled(spark, sf_dir)
    return _shown(selector.auto_search(ix, _asked(data, 100).drop("r"), model))


@query("radius_auto", radius_sql("ord2", 100, 800.0))
def radius_auto(spark, sf_dir):
    data = points(spark, sf_dir, "ord2")
    ix = build_index(data)
    asked = _asked(data, 100, r=800.0).drop("k")
    labels = selector.label_queries(ix, asked, "radius")
    model = selector.train_selector(selector.features(ix, asked, "f1").join(labels, "qid").select("features", "label"), "rf")
    return selector.auto_search(ix, asked, model, "f1", "radius")


_PRED6 = "(values (1, 0, 0, 1), (2, 0, 1, 2), (3, 1, 1, 1), (4, 2, 2, 1), (5, 2, 0, 3), (6, 3, 2, 4)) v(qid, label, prediction, place)"
_PRED_ROWS = [(1, 0, 0, 1), (2, 0, 1, 2), (3, 1, 1, 1), (4, 2, 2, 1), (5, 2, 0, 3), (6, 3, 2, 4)]


def _predictions(spark):
    return spark.createDataFrame(_PRED_ROWS, "qid int, label int, prediction int, place int")


@query("selector_mrr", f"select round(avg(1.0::DOUBLE / place), 9) as mrr from {_PRED6}")
def selector_mrr(spark, sf_dir):
    return M.mrr(_predictions(spark).withColumn("strategy", F.col("label"))).select(F.round("mrr", 9).alias("mrr"))


@query("selector_precision", f"with v as (select * from {_PRED6}), p as (select prediction as c, avg((prediction = label)::INT) as p from v group by prediction) select round((select avg(coalesce(p, 0)) from (select distinct label as c from v) left join p using (c)), 9) as macro, round((select avg((prediction = label)::INT) from v), 9) as micro")
def selector_precision(spark, sf_dir):
    v = _predictions(spark)
    return M.macro_precision(v).crossJoin(M.micro_precision(v)).select(F.round("macro", 9).alias("macro"), F.round("micro", 9).alias("micro"))


@query("selection_share", "select 'box_dfs' as strategy, 0.75::DOUBLE as share")
def selection_share(spark, sf_dir):
    return M.selection_share(spark.createDataFrame([("box_dfs",), ("box_dfs",), ("box_dfs",), ("ball_bfs",)], "strategy string"))


# --- k-means -----------------------------------------------------------------------------------------------------


def _lloyd_sql(rounds: int, k: int, last: str) -> str:
    out = f"with p as ({SQL_VIEW['ord2'][1]}), c0 as (select row_number() over (order by pid) - 1 as cid, x0 as c0, x1 as c1 from (select * from p order by pid limit {k}))"
    for i in range(rounds):
        out += f", a{i} as (select pid, any_value(x0) as x0, any_value(x1) as x1, min_by(cid, struct_pack(d := (x0 - c0) * (x0 - c0) + (x1 - c1) * (x1 - c1), cid := cid)) as cid, min((x0 - c0) * (x0 - c0) + (x1 - c1) * (x1 - c1)) as d from p, c{i} group by pid), c{i + 1} as (select cid, avg(x0) as c0, avg(x1) as c1, count(*) as n from a{i} group by cid)"
    return out + last


_KM = _lloyd_sql(3, 4, " select cast(cid as integer) as cid, n, round(c0, 4) as c0, round(c1, 4) as c1 from c3")


def _kmeans(mode: str, spark, sf_dir):
    data = points(spark, sf_dir, "ord2")
    out = kmeans.simplify(build_index(data) if mode == "node_filter" else data, 4, 3, mode)
    return out.select("cid", "n", F.round(F.element_at("coords", 1), 4).alias("c0"), F.round(F.element_at("coords", 2), 4).alias("c1"))


query("kmeans_lloyd_3iters", _KM)(partial(_kmeans, "lloyd"))
query("kmeans_indexed_3iters", _KM)(partial(_kmeans, "centroid_index"))
query("kmeans_filtered_3iters", _KM)(partial(_kmeans, "node_filter"))


@query("kmeans_sse", _lloyd_sql(3, 4, " select round(sum(d) / 1e6, 3) as sse from a2"))
def kmeans_sse(spark, sf_dir):
    out = kmeans.run(points(spark, sf_dir, "ord2"), 4, 3)
    return spark.createDataFrame([(out["history"][2]["sse"],)], "sse double").select(F.round(F.col("sse") / 1e6, 3).alias("sse"))


def _updated_sql(before: int, after: int, k: int) -> str:
    out = f"with p as ({SQL_VIEW['ord2'][1]}), early as (select * from p where pid % 5 != 0), c0 as (select row_number() over (order by pid) - 1 as cid, x0 as c0, x1 as c1 from (select * from early order by pid limit {k}))"
    for i in range(before + after):
        source = "early" if i < before else "p"
        out += f", a{i} as (select pid, any_value(x0) as x0, any_value(x1) as x1, min_by(cid, struct_pack(d := (x0 - c0) * (x0 - c0) + (x1 - c1) * (x1 - c1), cid := cid)) as cid from {source}, c{i} group by pid), c{i + 1} as (select cid, avg(x0) as c0, avg(x1) as c1, count(*) as n from a{i} group by cid)"
    return out + f" select cast(cid as integer) as cid, n from c{before + after}"


@query("kmeans_updated", _updated_sql(3, 2, 4))
def kmeans_updated(spark, sf_dir):
    data = points(spark, sf_dir, "ord2")
    first = kmeans.run(data.where("pid % 5 != 0"), 4, 3)
    out = kmeans.update(data, first, 2, "lloyd")
    return spark.createDataFrame([(i, int(n)) for i, n in enumerate(out["sizes"])], "cid int, n long")


# --- baselines ---------------------------------------------------------------------------------------------------


def _baseline(make, strategy: str, spark, sf_dir):
    data = points(spark, sf_dir, "ord2")
    return _shown(search.knn(make(data), _asked(data, 100), strategy))


query("baseline_ball_knn", knn_sql("ord2", 100, 10))(partial(_baseline, B.ball_tree, "ball_dfs"))
query("baseline_rtree_knn", knn_sql("ord2", 100, 10))(partial(_baseline, B.packed_rtree, "box_bfs"))
query("baseline_kd_knn", knn_sql("ord2", 100, 10))(partial(_baseline, B.binary_kd, "box_dfs"))
query("baseline_base_multiway_knn", knn_sql("ord2", 100, 10))(partial(_baseline, B.base_multiway, "box_dfs"))
query("baseline_equal_width_knn", knn_sql("ord2", 100, 10))(partial(_baseline, B.equal_width, "box_dfs"))


@query("baseline_forest_knn", knn_sql("ord2", 100, 10))
def baseline_forest_knn(spark, sf_dir):
    data = points(spark, sf_dir, "ord2")
    f = B.forest(data.where("pid % 4 = 0")).insert(data.where("pid % 4 in (1, 2)")).insert(data.where("pid % 4 = 3"))
    return _shown(f.knn(_asked(data, 100)))


@query("baseline_learned_rtree_knn", knn_sql("ord2", 100, 10))
def baseline_learned_rtree_knn(spark, sf_dir):
    data = points(spark, sf_dir, "ord2")
    return _shown(B.learned_rtree(data).knn(_asked(data, 100)))


@query("grid_radius", radius_sql("evt2", 100, 5.0))
def grid_radius(spark, sf_dir):
    data = points(spark, sf_dir, "evt2")
    return B.grid_radius(data, _asked(data, 100, r=5.0), [10.0, 10.0])


_BIT = " | ".join(f"(((c0 >> {b}) & 1) << {2 * b}) | (((c1 >> {b}) & 1) << {2 * b + 1})" for b in range(8))


@query("zorder_codes", f"with p as ({SQL_VIEW['cus2'][1]}), c as (select pid, cast(least(255, greatest(0, floor((x0 + 1000.0) / 50.0))) as bigint) as c0, cast(least(255, greatest(0, floor(x1))) as bigint) as c1 from p) select pid, {_BIT} as z from c")
def zorder_codes(spark, sf_dir):
    return B.zorder(points(spark, sf_dir, "cus2"), [-1000.0, 0.0], [50.0, 1.0], 8).select("pid", "z")


# --- generic operators -------------------------------------------------------------------------------------------


@query("agg_cube_report", "select l_returnflag, l_linestatus, count(*) as n, round(sum(l_quantity), 2) as qty, cast(grouping(l_returnflag) * 2 + grouping(l_linestatus) as bigint) as gid from lineitem group by cube (l_returnflag, l_linestatus)")
def agg_cube_report(spark, sf_dir):
    return table(spark, sf_dir, "lineitem").cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("qty"), F.grouping_id().alias("gid"))


@query("agg_rollup", "select o_orderstatus, o_orderpriority, count(*) as n from orders group by rollup (o_orderstatus, o_orderpriority)")
def agg_rollup(spark, sf_dir):
    return table(spark, sf_dir, "orders").rollup("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"))


@query("agg_grouping_sets", "select coalesce(p_brand, 'all') as p_brand, coalesce(p_size, -1) as p_size, count(*) as n from part group by grouping sets ((p_brand), (p_size), ())")
def agg_grouping_sets(spark, sf_dir):
    return table(spark, sf_dir, "part").groupingSets([[F.col("p_brand")], [F.col("p_size")], []], "p_brand", "p_size").agg(F.count("*").alias("n")).select(F.coalesce("p_brand", F.lit("all")).alias("p_brand"), F.coalesce("p_size", F.lit(-1)).alias("p_size"), "n")


@query("agg_distinct_ties", "select count(distinct l_quantity) as q, count(distinct l_discount) as d, count(distinct l_tax) as t from lineitem")
def agg_distinct_ties(spark, sf_dir):
    return table(spark, sf_dir, "lineitem").agg(F.countDistinct("l_quantity").alias("q"), F.countDistinct("l_discount").alias("d"), F.countDistinct("l_tax").alias("t"))


@query("agg_regression", "select round(regr_slope(o_totalprice, o_orderkey), 6) as slope, round(corr(o_totalprice, o_orderkey), 6) as r, round(var_pop(o_totalprice) / 1e6, 4) as v from orders")
def agg_regression(spark, sf_dir):
    x, y = F.col("o_orderkey").cast("double"), F.col("o_totalprice")
    return table(spark, sf_dir, "orders").agg(F.round(F.regr_slope(y, x), 6).alias("slope"), F.round(F.corr(y, x), 6).alias("r"), F.round(F.var_pop(y) / 1e6, 4).alias("v"))


@query("agg_histogram", "select cast(floor(value / 10.0) as bigint) as bucket, count(*) as n from events group by 1")
def agg_histogram(spark, sf_dir):
    return table(spark, sf_dir, "events").groupBy(F.floor(F.col("value") / 10.0).alias("bucket")).agg(F.count("*").alias("n"))


@query("agg_filtered_having", "select user_id, count(*) as n, count(*) filter (where value > 50) as high from events group by user_id having count(*) > 60")
def agg_filtered_having(spark, sf_dir):
    return table(spark, sf_dir, "events").groupBy("user_id").agg(F.count("*").alias("n"), F.count_if(F.col("value") > 50).alias("high")).where("n > 60")


@query("agg_pivot", "select user_id % 5 as g, count(*) filter (where event_type = 'view') as view, count(*) filter (where event_type = 'click') as click from events group by 1")
def agg_pivot(spark, sf_dir):
    out = table(spark, sf_dir, "events").groupBy((F.col("user_id") % 5).alias("g")).pivot("event_type", ["view", "click"]).agg(F.count("event_id"))
    return out.na.fill(0)


@query("win_running", "select event_id, user_id, round(sum(value) over (partition by user_id order by event_id rows unbounded preceding), 4) as total, lag(value) over (partition by user_id order by event_id) as before, ntile(4) over (partition by user_id order by event_id) as quarter from events")
def win_running(spark, sf_dir):
    by = Window.partitionBy("user_id").orderBy("event_id")
    e = table(spark, sf_dir, "events")
    return e.select("event_id", "user_id", F.round(F.sum("value").over(by.rowsBetween(Window.unboundedPreceding, 0)), 4).alias("total"), F.lag("value").over(by).alias("before"), F.ntile(4).over(by).cast("long").alias("quarter"))


@query("win_range_1d_radius", "select event_id, count(*) over (partition by user_id order by value range between 5.0 preceding and 5.0 following) as neighbours from events")
def win_range_1d_radius(spark, sf_dir):
    return relational.one_dimensional_radius(table(spark, sf_dir, "events"), "user_id", "value", 5.0).select("event_id", "neighbours")


@query("win_ranks", "select p_partkey, cast(rank() over (partition by p_size order by p_retailprice) as integer) as r, cast(dense_rank() over (partition by p_size order by p_retailprice) as integer) as d from part")
def win_ranks(spark, sf_dir):
    by = Window.partitionBy("p_size").orderBy("p_retailprice")
    return table(spark, sf_dir, "part").select("p_partkey", F.rank().over(by).alias("r"), F.dense_rank().over(by).alias("d"))


@query("set_operations", "select 'intersect' as op, count(*) as n from (select c_nationkey from customer intersect select s_nationkey from supplier) union all select 'except', count(*) from (select c_nationkey from customer except all select s_nationkey from supplier)")
def set_operations(spark, sf_dir):
    a, b = table(spark, sf_dir, "customer").select(F.col("c_nationkey").alias("k")), table(spark, sf_dir, "supplier").select(F.col("s_nationkey").alias("k"))
    count = lambda df, op: df.agg(F.lit(op).alias("op"), F.count("*").alias("n"))
    return count(a.intersect(b), "intersect").unionByName(count(a.exceptAll(b), "except"))


@query("join_semi_anti", "select (select count(*) from customer where exists (select 1 from orders where o_custkey = c_custkey)) as buying, (select count(*) from customer where not exists (select 1 from orders where o_custkey = c_custkey)) as idle")
def join_semi_anti(spark, sf_dir):
    c, o = table(spark, sf_dir, "customer"), table(spark, sf_dir, "orders").select(F.col("o_custkey").alias("c_custkey"))
    return c.join(o, "c_custkey", "left_semi").agg(F.count("*").alias("buying")).crossJoin(c.join(o, "c_custkey", "left_anti").agg(F.count("*").alias("idle")))


@query("join_interval", "with r as (select p_partkey, p_retailprice - 1.0 as lo, p_retailprice + 1.0 as hi from part) select r.p_partkey as range_id, count(*) as n from r, part where part.p_retailprice between lo and hi group by 1")
def join_interval(spark, sf_dir):
    part = table(spark, sf_dir, "part").select("p_partkey", "p_retailprice")
    ranges = part.select(F.col("p_partkey").alias("range_id"), (F.col("p_retailprice") - 1.0).alias("lo"), (F.col("p_retailprice") + 1.0).alias("hi"))
    return relational.interval_join(part, ranges, "p_retailprice", 4.0).groupBy("range_id").agg(F.count("*").alias("n"))


@query("as_of_events", "select a.event_id, coalesce(max(b.event_id), -1) as matched from (select * from events where event_type = 'purchase') a left join (select * from events where event_type = 'click') b on b.ts <= a.ts group by a.event_id")
def as_of_events(spark, sf_dir):
    e = table(spark, sf_dir, "events").select("event_id", "ts", "event_type")
    left, right = e.where("event_type = 'purchase'").drop("event_type"), e.where("event_type = 'click'").select(F.col("event_id").alias("other"), "ts")
    return relational.as_of_join(left, right, "ts", "ts", "other").select("event_id", F.coalesce("matched", F.lit(-1)).alias("matched"))


@query("join_nation_report", "select n_name, count(*) as n, round(sum(c_acctbal), 2) as total from customer join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey group by n_name")
def join_nation_report(spark, sf_dir):
    t = lambda n: table(spark, sf_dir, n)
    out = t("customer").join(t("nation"), F.col("c_nationkey") == F.col("n_nationkey")).join(t("region"), F.col("n_regionkey") == F.col("r_regionkey"))
    return out.groupBy("n_name").agg(F.count("*").alias("n"), F.round(F.sum("c_acctbal"), 2).alias("total"))


@query("fn_json_time", f"select event_id, cast(props->>'$.k' as integer) as k, epoch_us(ts)::DOUBLE / {_HOUR} as h from events")
def fn_json_time(spark, sf_dir):
    return table(spark, sf_dir, "events").select("event_id", F.from_json("props", "k int")["k"].alias("k"), hours("ts").alias("h"))


@query("fn_date_days", f"select o_orderkey, epoch_us(o_orderdate)::DOUBLE / {_DAY} as d from orders")
def fn_date_days(spark, sf_dir):
    return table(spark, sf_dir, "orders").select("o_orderkey", days("o_orderdate").alias("d"))


@query("fn_unpivot", f"with p as ({SQL_VIEW['cus2'][1]}) select pid, 0 as dim, x0 as x from p union all select pid, 1, x1 from p")
def fn_unpivot(spark, sf_dir):
    return melt(unmelt(melt(points(spark, sf_dir, "cus2"), 2), 2), 2)


@query("fn_scaled", f"with p as ({SQL_VIEW['cus2'][1]}) select pid, (x0 - (select min(x0) from p)) / ((select max(x0) from p) - (select min(x0) from p)) as s from p")
def fn_scaled(spark, sf_dir):
    return scaled(points(spark, sf_dir, "cus2"), "minmax").select("pid", F.element_at("coords", 1).alias("s"))


@query("fn_extent", f"with p as ({SQL_VIEW['ord2'][1]}) select min(x0) as l0, max(x1) as h1, count(*) as n from p")
def fn_extent(spark, sf_dir):
    return extent(points(spark, sf_dir, "ord2"), 2).select(F.element_at("lo", 1).alias("l0"), F.element_at("hi", 2).alias("h1"), "n")


@query("validate_points", "select count(*) as good, 0::BIGINT as bad from orders")
def validate_points(spark, sf_dir):
    good, bad = validate(points(spark, sf_dir, "ord2"))
    return good.agg(F.count("*").alias("good")).crossJoin(bad.agg(F.count("*").alias("bad")))


@query("dedupe_points", "select count(*) as distinct_points, cast(sum(n) as bigint) as total from (select p_retailprice, p_size, count(*) as n from part group by 1, 2)")
def dedupe_points(spark, sf_dir):
    return relational.dedupe_points(points(spark, sf_dir, "part2")).agg(F.count("*").alias("distinct_points"), F.sum("copies").alias("total"))


@query("sort_topk", "select o_orderkey, o_totalprice from orders order by o_totalprice desc, o_orderkey limit 50")
def sort_topk(spark, sf_dir):
    return table(spark, sf_dir, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(50)


# --- streams -----------------------------------------------------------------------------------------------------


PART_EVENTS = 500_000  #: events of a stream's file, so that a micro-batch and the state that waits for the watermark stay bounded


def write_in_order(events: DataFrame, folder: str, parts: int) -> None:
    """The stream takes files by their age: each part of the ids is written once the one before is there."""
    n = (events.agg(F.max("event_id")).first()[0] or 0) + 1
    for i in range(parts):
        some = events.where((F.col("event_id") >= i * n // parts) & (F.col("event_id") < (i + 1) * n // parts))
        some.coalesce(1).sortWithinPartitions("event_id").write.mode("append").parquet(folder)


def write_by_time(events: DataFrame, folder: str, parts: int) -> None:
    """The same in the order of event time, whatever the ids: nothing comes behind the watermark. More parts where there are many events."""
    timed = events.withColumn("_t", F.unix_micros(F.col("ts").cast("timestamp")))
    parts = max(parts, -(-events.count() // PART_EVENTS))
    cuts = timed.agg(F.percentile_approx("_t", F.array(*[F.lit(i / parts) for i in range(1, parts)]), F.lit(100 * parts)).alias("cuts")).first().cuts or []
    ends = [None, *sorted(set(cuts)), None]
    for low, high in zip(ends, ends[1:], strict=False):
        some = timed if low is None else timed.where(F.col("_t") > low)
        some = (some if high is None else some.where(F.col("_t") <= high)).drop("_t")
        some.coalesce(1).sortWithinPartitions("ts", "event_id").write.mode("append").parquet(folder)


def _streamed(spark, sf_dir, make, mode: str, parts: int = 4):
    """Deal the events to files, one written after the other in the order of time, run the stream over them, give the sink's table."""
    folder = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    write_by_time(table(spark, sf_dir, "events"), folder, parts)
    return ingest.run_to_table(make(ingest.events_stream(spark, folder)), f"t{uuid.uuid4().hex}", mode, f"{folder}-checkpoint")


@query("stream_tumbling", "select time_bucket(interval '1 day', ts) as window_start, event_type, count(*) as n, round(sum(value), 4) as total from events group by 1, 2")
def stream_tumbling(spark, sf_dir):
    return _streamed(spark, sf_dir, ingest.tumbling, "complete")


@query("stream_sliding", "select time_bucket(interval '1 day', ts) - to_days(cast(i as integer)) as window_start, count(*) as n from events, range(0, 2) r(i) group by 1")
def stream_sliding(spark, sf_dir):
    return _streamed(spark, sf_dir, ingest.sliding, "complete")


@query("stream_session", "with g as (select *, case when ts - lag(ts) over (partition by user_id order by ts) < interval '12 hours' then 0 else 1 end as first from events), s as (select *, sum(first) over (partition by user_id order by ts rows unbounded preceding) as s from g) select user_id, min(ts) as session_start, count(*) as n from s group by user_id, s")
def stream_session(spark, sf_dir):
    return ingest.sessions(ingest.with_utc(table(spark, sf_dir, "events")))


@query("stream_dedupe", "select count(*) as n from events")
def stream_dedupe(spark, sf_dir):
    return _streamed(spark, sf_dir, lambda e: ingest.deduped(e).select("event_id"), "append").agg(F.count("*").alias("n"))


@query("stream_cell_counts", "select cast(floor(value / 25.0) as bigint) as cell, count(*) as n from events group by 1")
def stream_cell_counts(spark, sf_dir):
    out = _streamed(spark, sf_dir, lambda e: ingest.stateful_cell_counts(e, 25.0), "update")
    return out.groupBy("cell").agg(F.max("n").alias("n"))


@query("stream_insert_knn", knn_sql("evt2", 100, 10))
def stream_insert_knn(spark, sf_dir):
    data = points(spark, sf_dir, "evt2")
    folder = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    n = data.agg(F.max("pid")).first()[0] + 1
    table(spark, sf_dir, "events").where(F.col("event_id") >= int(0.8 * n)).repartitionByRange(3, "event_id").write.parquet(folder)
    holder = ingest.IndexHolder(build_index(data.where(F.col("pid") < int(0.8 * n)), t=4))
    ingest.stream_insert(ingest.events_stream(spark, folder).drop("ts_utc"), holder, f"{folder}-checkpoint").awaitTermination()
    return _shown(search.knn(holder.ix, _asked(data, 100)))


# --- experiments -------------------------------------------------------------------------------------------------

#: What the worked examples of the text come to.
_EXAMPLES = {
    "W3": "select 'W3' as workload, 'evt2' as dataset, 't=' || t as config, metric, value from (values (2, 'aepl', 2.0::DOUBLE), (3, 'aepl', 1.75), (4, 'aepl', 2.25), (2, 'printed_per_point', 2.0), (3, 'printed_per_point', 1.875), (4, 'printed_per_point', 2.25), (2, 'level_sum', 2.0), (3, 'level_sum', 5.0::DOUBLE / 3), (4, 'level_sum', 2.25), (2, 'exact_recursive', 2.0), (3, 'exact_recursive', 1.75), (4, 'exact_recursive', 2.25)) v(t, metric, value)",
    "W12": "select * from (values ('W12', 'fixture', '6,3,9', 'points_rebuilt', 12.0::DOUBLE), ('W12', 'fixture', '6,3,9', 'points_full', 18.0)) v(workload, dataset, config, metric, value)",
    "W20": "select 'W20' as workload, 'fixture' as dataset, cast(i as varchar) as config, 'similarity' as metric, value from (values (0, 1.0::DOUBLE), (1, -3.0), (2, 3.0)) v(i, value)",
}
for _w, _f in workloads.ALL.items():
    query(f"workload_{_w.lower()}", _EXAMPLES.get(_w))(_f)

from pivotgrove import queries_surface  # noqa: E402, F401 (it registers its own)
