"""Distances, bounding volumes and pruning tests as Column expressions over coordinate arrays."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def dist2(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x)


def dist(a: Column, b: Column) -> Column:
    return F.sqrt(dist2(a, b))


def flat_dist(a: list[Column], b: list[Column]) -> Column:
    """Distance over flat columns: stays inside whole-stage codegen."""
    total = None
    for x, y in zip(a, b, strict=True):
        term = (x - y) * (x - y)
        total = term if total is None else total + term
    return F.sqrt(total)


def mbr(df: DataFrame, keys: list[str], d: int, coords: str = "coords") -> DataFrame:
    """Bounding box of each group: (keys, lo, hi, n_points); partial aggregation before the exchange."""
    at = lambda i: F.element_at(coords, i + 1)
    lows, highs = [F.min(at(i)).alias(f"l{i}") for i in range(d)], [F.max(at(i)).alias(f"h{i}") for i in range(d)]
    out = df.groupBy(*keys).agg(*lows, *highs, F.count("*").alias("n_points"))
    return out.select(*keys, F.array(*[f"l{i}" for i in range(d)]).alias("lo"), F.array(*[f"h{i}" for i in range(d)]).alias("hi"), "n_points")


def mbb(df: DataFrame, keys: list[str], d: int, coords: str = "coords") -> DataFrame:
    """Bounding ball of each group around its centroid: (keys, center, radius, n_points)."""
    means = [F.avg(F.element_at(coords, i + 1)).alias(f"m{i}") for i in range(d)]
    centre = df.groupBy(*keys).agg(*means, F.count("*").alias("n_points")).select(*keys, F.array(*[f"m{i}" for i in range(d)]).alias("center"), "n_points")
    reach = df.join(centre, keys).groupBy(*keys).agg(F.max(dist(F.col(coords), F.col("center"))).alias("radius"))
    return centre.join(reach, keys).select(*keys, "center", "radius", "n_points")


def mbb_merge(children: DataFrame, keys: list[str], d: int) -> DataFrame:
    """Parent balls from child balls (center, radius, n_points): weighted centre, a radius that covers every child."""
    total = F.sum("n_points")
    means = [(F.sum(F.element_at("center", i + 1) * F.col("n_points")) / total).alias(f"m{i}") for i in range(d)]
    centre = children.groupBy(*keys).agg(*means, total.alias("total")).select(*keys, F.array(*[f"m{i}" for i in range(d)]).alias("parent_center"), "total")
    reach = children.join(centre, keys).groupBy(*keys).agg(F.max(dist(F.col("center"), F.col("parent_center")) + F.col("radius")).alias("radius"))
    return centre.join(reach, keys).select(*keys, F.col("parent_center").alias("center"), "radius", F.col("total").alias("n_points"))


def boxes_overlap(lo: Column, hi: Column, qlo: Column, qhi: Column) -> Column:
    """Closed boxes that touch overlap; a query box that does not overlap rules the data box out."""
    return F.forall(F.arrays_zip(lo.alias("a"), hi.alias("b"), qlo.alias("c"), qhi.alias("e")), lambda z: (z["a"] <= z["e"]) & (z["c"] <= z["b"]))


def ball_prunes(center: Column, radius: Column, q: Column, r: Column) -> Column:
    return dist(center, q) > radius + r


def ball_lower_bound(center: Column, radius: Column, q: Column) -> Column:
    return F.greatest(dist(center, q) - radius, F.lit(0.0))


def ball_upper_bound(center: Column, radius: Column, q: Column) -> Column:
    return dist(center, q) + radius


def box_lower_bound(lo: Column, hi: Column, q: Column) -> Column:
    gaps = F.zip_with(F.arrays_zip(lo.alias("a"), hi.alias("b")), q, lambda z, x: F.greatest(z["a"] - x, x - z["b"], F.lit(0.0)))
    return F.sqrt(F.aggregate(gaps, F.lit(0.0), lambda s, g: s + g * g))


def box_upper_bound(lo: Column, hi: Column, q: Column) -> Column:
    """Distance to the farthest corner."""
    gaps = F.zip_with(F.arrays_zip(lo.alias("a"), hi.alias("b")), q, lambda z, x: F.greatest(F.abs(x - z["a"]), F.abs(x - z["b"])))
    return F.sqrt(F.aggregate(gaps, F.lit(0.0), lambda s, g: s + g * g))


def box_prunes(lo: Column, hi: Column, q: Column, r: Column) -> Column:
    return box_lower_bound(lo, hi, q) > r


def query_box(q: Column, r: Column) -> tuple[Column, Column]:
    return F.transform(q, lambda x: x - r), F.transform(q, lambda x: x + r)


def register_sql(spark) -> None:
    """box_lower_bound(lo, hi, q), ball_lower_bound(center, radius, q), point_dist(a, b) as temporary SQL functions."""
    spark.sql("create or replace temporary function point_dist(a array<double>, b array<double>) returns double return sqrt(aggregate(zip_with(a, b, (x, y) -> (x - y) * (x - y)), 0D, (s, x) -> s + x))")
    spark.sql("create or replace temporary function box_lower_bound(lo array<double>, hi array<double>, q array<double>) returns double return sqrt(aggregate(zip_with(zip_with(lo, hi, (a, b) -> named_struct('a', a, 'b', b)), q, (z, x) -> greatest(z.a - x, x - z.b, 0D)), 0D, (s, g) -> s + g * g))")
    spark.sql("create or replace temporary function ball_lower_bound(center array<double>, radius double, q array<double>) returns double return greatest(sqrt(aggregate(zip_with(center, q, (x, y) -> (x - y) * (x - y)), 0D, (s, x) -> s + x)) - radius, 0D)")
