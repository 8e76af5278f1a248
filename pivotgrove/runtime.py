"""What every operator needs from the session: shipped code, a shared folder, materialised tables, components."""

from __future__ import annotations

import os
import tempfile
import uuid
import zipfile
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

_PACKAGE = Path(__file__).resolve().parent


_BATCH = "spark.sql.execution.arrow.maxBytesPerBatch"
_BATCH_DEFAULT, BATCH_BYTES = "67108864b", "4m"


def ship(spark: SparkSession) -> None:
    """Send this package to the executors once per application, so that Python kernels import there.

    Batches on their way to a kernel are held several times over, by the JVM and by Python: unless the session says
    otherwise they are kept to BATCH_BYTES, whatever the length of their rows.
    """
    context = spark.sparkContext
    if spark.conf.get(_BATCH) == _BATCH_DEFAULT:
        spark.conf.set(_BATCH, BATCH_BYTES)
    if getattr(context, "_pivotgrove_shipped", False):
        return
    folder = os.path.realpath(tempfile.mkdtemp(prefix="pivotgrove-"))
    archive = os.path.join(folder, "pivotgrove_code.zip")
    with zipfile.ZipFile(archive, "w") as out:
        for path in sorted(_PACKAGE.rglob("*.py")):
            out.write(path, str(Path(_PACKAGE.name) / path.relative_to(_PACKAGE)))
    context.addPyFile(archive)
    context._pivotgrove_shipped = True


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir; in local mode one of our own where it is unset."""
    context = spark.sparkContext
    found = context.getConf().get("spark.checkpoint.dir") or context.getCheckpointDir()
    if not found:
        if not context.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        found = "file://" + os.path.realpath(tempfile.mkdtemp(prefix="pivotgrove-shared-"))
        context.setCheckpointDir(found)
    return found.rstrip("/")


def give_back() -> None:
    """Hand this process's free memory to the system: a Python worker outlives its task, and idles beside the next stage."""
    import ctypes

    import pyarrow as pa

    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # of glibc
    if trim is not None:
        trim(0)


def giving_back(kernel):
    """The kernel, which hands back what it used when its task ends."""

    def run(batches):
        yield from kernel(batches)
        give_back()

    return run


_CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def materialise(df: DataFrame, label: str) -> DataFrame:
    """Write df to the shared folder and read it back: lineage is cut and lost executors cost nothing.

    The shuffle files behind the write go with it, as nothing reads them again; discard() takes the table itself.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}"
    before = spark.conf.get(_CLEANUP, None)
    spark.conf.set(_CLEANUP, "true")
    try:
        df.write.parquet(path)
    finally:
        if before is None:
            spark.conf.unset(_CLEANUP)
        else:
            spark.conf.set(_CLEANUP, before)
    out = spark.read.schema(df.schema).parquet(path)
    out._materialised_at = path
    return out


def discard(*tables: DataFrame) -> None:
    """Delete tables that materialise() returned and that no later plan reads."""
    for table in tables:
        if path := table.__dict__.get("_materialised_at"):
            where = table.sparkSession._jvm.org.apache.hadoop.fs.Path(path)
            where.getFileSystem(table.sparkSession._jsc.hadoopConfiguration()).delete(where, True)


_CONTRACT_EDGES = 250_000


def _contract(batches):
    """Replace the links of each bounded run by stars: every node linked to the smallest it reaches in the run."""
    import pyarrow as pa

    parent: dict = {}

    def root(x):
        while (up := parent.setdefault(x, x)) != x:
            parent[x] = x = parent[up]
        return x

    def stars(schema):
        pairs = [(root(x), x) for x in list(parent)]
        pairs = [p for p in pairs if p[0] != p[1]]
        parent.clear()
        return pa.RecordBatch.from_arrays([pa.array([p[i] for p in pairs], schema.field(i).type) for i in (0, 1)], ["lo", "hi"])

    seen, schema = 0, None
    for batch in batches:
        schema = batch.schema
        for a, b in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
            a, b = root(a), root(b)
            if a != b:
                parent[max(a, b)] = min(a, b)
        seen += batch.num_rows
        if seen >= _CONTRACT_EDGES:
            yield stars(schema)
            seen = 0
    if seen:
        yield stars(schema)


def components(edges: DataFrame, src: str = "src", dst: str = "dst", max_rounds: int = 50) -> DataFrame:
    """(node, root) for every node of edges; root is the smallest node reachable.

    Each round first contracts the links inside every partition, in runs of bounded size, then alternates two
    steps over all: every node hands its larger neighbours to its smallest one, then every node hands its
    smaller neighbours and itself to the smallest. Both are a partial-aggregated minimum and a join; the links
    are written to the shared folder each round. Self-links, repeated links and null ends are dropped; an empty
    frame gives an empty frame.
    """
    ship(edges.sparkSession)
    kind = edges.schema[src].dataType.simpleString()
    local = lambda df: df.distinct().mapInArrow(giving_back(_contract), f"lo {kind}, hi {kind}")
    low, high = F.least(src, dst), F.greatest(src, dst)
    links = materialise(local(edges.where(F.col(src) != F.col(dst)).select(low.alias("lo"), high.alias("hi"))), "links")
    for _ in range(max_rounds):
        # Done when the links form stars: no node is both a centre and a leaf, and no leaf has two centres.
        roles = links.select(F.col("hi").alias("n"), F.lit(1).alias("leaf"), F.lit(0).alias("centre")).union(links.select(F.col("lo"), F.lit(0), F.lit(1)))
        if roles.groupBy("n").agg(F.sum("leaf").alias("leaf"), F.max("centre").alias("centre")).where("leaf > 1 or (leaf > 0 and centre > 0)").isEmpty():
            return links.select(F.col("hi").alias("node"), F.col("lo").alias("root")).union(links.select("lo", F.col("lo").alias("r")).distinct())
        # Large star: a node's larger neighbours move to the smallest of it and all its neighbours.
        both = links.union(links.select("hi", "lo")).toDF("u", "v")
        least = both.groupBy("u").agg(F.min("v").alias("m")).select(F.col("u").alias("lo"), F.least("m", "u").alias("m"))
        large = links.join(least, "lo").select(F.col("m").alias("lo"), "hi").where("lo < hi").distinct()
        # Small star: a node's smaller neighbours, and it, move to the smallest of them.
        moved = large.join(large.groupBy("hi").agg(F.min("lo").alias("m")), "hi")
        older, links = links, materialise(local(moved.where("lo > m").select(F.col("m").alias("lo"), F.col("lo").alias("hi")).union(moved.select(F.col("m").alias("lo"), "hi"))), "links")
        discard(older)
    raise RuntimeError(f"components did not settle in {max_rounds} rounds")
