"""Point views over the given tables, point files, validation and stable ids."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

POINT_SCHEMA = T.StructType([T.StructField("pid", T.LongType()), T.StructField("coords", T.ArrayType(T.DoubleType()))])
EVENT_SCHEMA = T.StructType([T.StructField("event_id", T.LongType()), T.StructField("ts", T.TimestampNTZType()), T.StructField("user_id", T.LongType()), T.StructField("event_type", T.StringType()), T.StructField("value", T.DoubleType()), T.StructField("props", T.StringType())])


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def micros(column: str) -> Column:
    """Microseconds since 1970 of a zone-less timestamp, whatever the session zone."""
    return F.expr(f"timestampdiff(MICROSECOND, timestamp_ntz'1970-01-01 00:00:00', {column})")


def days(column: str) -> Column:
    return micros(column) / F.lit(86_400_000_000.0)


def hours(column: str) -> Column:
    return micros(column) / F.lit(3_600_000_000.0)


def to_double(*columns: Column | str) -> Column:
    return F.array(*[(F.col(c) if isinstance(c, str) else c).try_cast("double") for c in columns])


def line_key() -> Column:
    """An id for lineitem: its four key columns are unique together."""
    return F.xxhash64("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")


#: view -> (table, id, coordinates)
VIEWS: dict[str, tuple[str, Column | str, list]] = {
    "ord2": ("orders", "o_orderkey", ["o_totalprice", ("days", "o_orderdate")]),
    "evt2": ("events", "event_id", ["value", ("hours", "ts")]),
    "evt3": ("events", "event_id", ["value", ("hours", "ts"), "user_id"]),
    "evt4": ("events", "event_id", ["value", ("hours", "ts"), "user_id", ("json", "props")]),
    "li2": ("lineitem", "line", ["l_extendedprice", ("days", "l_shipdate")]),
    "li3": ("lineitem", "line", ["l_extendedprice", ("days", "l_shipdate"), "l_quantity"]),
    "li4": ("lineitem", "line", ["l_extendedprice", ("days", "l_shipdate"), "l_quantity", "l_discount"]),
    "part2": ("part", "p_partkey", ["p_retailprice", "p_size"]),
    "cus2": ("customer", "c_custkey", ["c_acctbal", "c_nationkey"]),
    "emb3": ("embeddings", "vec_id", [("slice", 3)]),
    "emb64": ("embeddings", "vec_id", [("slice", 64)]),
}


def view_of(df: DataFrame, view: str) -> DataFrame:
    """(pid, coords) of a table's rows; only the columns of the view are read."""
    _, pid, parts = VIEWS[view]
    columns: list = []
    for part in parts:
        if isinstance(part, str):
            columns.append(F.col(part))
        elif part[0] == "days":
            columns.append(days(part[1]))
        elif part[0] == "hours":
            columns.append(hours(part[1]))
        elif part[0] == "json":
            columns.append(F.from_json(part[1], "k int")["k"])
    coords = F.slice("embedding", 1, parts[0][1]).cast("array<double>") if parts[0][0] == "slice" else to_double(*columns)
    return df.select((line_key() if pid == "line" else F.col(pid).cast("long")).alias("pid"), coords.alias("coords"))


def points(spark: SparkSession, sf_dir: str, view: str) -> DataFrame:
    return view_of(table(spark, sf_dir, VIEWS[view][0]), view)


def is_point(coords: str = "coords") -> Column:
    """No null, NaN or infinite coordinate; of functions that Spark compiles. NaN is above infinity, and where a value is not found beside a null, that is unknown."""
    x, far = F.col(coords), F.lit(float("inf"))
    no_null = F.array_contains(x, far).isNotNull()
    return x.isNotNull() & ((F.size(x) == 0) | (no_null & (F.array_max(x) < far) & (F.array_min(x) > -far)))


def validate(df: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(points, quarantine): rows with a null id, or a null, NaN or infinite coordinate, are set aside."""
    good = F.col("pid").isNotNull() & F.coalesce(is_point(), F.lit(False))
    return df.where(good), df.where(~good)


def read_points(spark: SparkSession, path: str, fmt: str = "csv", coord_cols: tuple[str, ...] = ("x0", "x1"), pid: str = "pid") -> DataFrame:
    """Points of a CSV, JSON, ORC or Parquet file; lines that do not parse become null and go to quarantine."""
    schema = T.StructType([T.StructField(pid, T.LongType()), *[T.StructField(c, T.DoubleType()) for c in coord_cols]])
    reader = spark.read.schema(schema)
    if fmt in ("csv", "json"):
        reader = reader.option("mode", "PERMISSIVE")
    if fmt == "csv":
        reader = reader.option("header", True)
    return reader.format(fmt).load(path).select(F.col(pid).alias("pid"), F.array(*coord_cols).alias("coords"))


def write_points(df: DataFrame, path: str, fmt: str = "parquet") -> None:
    d = len(df.select("coords").first()["coords"])
    df.select("pid", *[F.element_at("coords", i + 1).alias(f"x{i}") for i in range(d)]).write.format(fmt).option("header", True).save(path)


def scaled(df: DataFrame, how: str = "none") -> DataFrame:
    """none, minmax or zscore over each coordinate: one aggregation, its single row joined back by broadcast."""
    if how == "none":
        return df
    d = len(df.select("coords").first()["coords"])
    x = lambda i: F.element_at("coords", i + 1)
    low, high = (F.min, F.max) if how == "minmax" else (F.avg, F.stddev_pop)
    ends = df.agg(F.array(*[low(x(i)) for i in range(d)]).alias("a"), F.array(*[high(x(i)) for i in range(d)]).alias("b"))
    width = (lambda a, b: b - a) if how == "minmax" else (lambda a, b: b)
    cut = F.transform(F.arrays_zip("coords", "a", "b"), lambda z: F.when(width(z["a"], z["b"]) == 0, 0.0).otherwise((z["coords"] - z["a"]) / width(z["a"], z["b"])))
    return df.crossJoin(F.broadcast(ends)).withColumn("coords", cut).drop("a", "b")


def melt(df: DataFrame, d: int) -> DataFrame:
    """(pid, dim, x): one row for each coordinate."""
    flat = df.select("pid", *[F.element_at("coords", i + 1).alias(str(i)) for i in range(d)])
    return flat.unpivot("pid", [str(i) for i in range(d)], "dim", "x").withColumn("dim", F.col("dim").cast("int"))


def unmelt(df: DataFrame, d: int) -> DataFrame:
    wide = df.groupBy("pid").pivot("dim", list(range(d))).agg(F.first("x"))
    return wide.select("pid", F.array(*[F.col(str(i)) for i in range(d)]).alias("coords"))


def extent(df: DataFrame, d: int) -> DataFrame:
    x = lambda i: F.element_at("coords", i + 1)
    return df.agg(F.array(*[F.min(x(i)) for i in range(d)]).alias("lo"), F.array(*[F.max(x(i)) for i in range(d)]).alias("hi"), F.count("*").alias("n"))
