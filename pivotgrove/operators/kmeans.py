"""k-means over points: Lloyd's rounds, assignment through an index of the centroids or by whole leaves."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pivotgrove.operators import tree
from pivotgrove.operators.index import IndexHandle, as_matrix
from pivotgrove.runtime import ship

MAX_CENTROIDS = 100_000  #: centroids go to every task


def initial(points: DataFrame, k: int) -> np.ndarray:
    """The points of the k lowest ids."""
    return np.array([r.coords for r in points.orderBy("pid").limit(k).collect()], dtype=float)


def nearest(x: np.ndarray, centroids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(centroid, squared distance) of each row, the lower centroid of equals; squares added in coordinate order."""
    total = np.zeros((len(x), len(centroids)))
    for i in range(x.shape[1]):
        gap = x[:, i][:, None] - centroids[:, i][None, :]
        total += gap * gap
    at = total.argmin(1)
    return at, total[np.arange(len(x)), at]


_SUMS = "cid int, n long, sums array<double>, sse double, point_tests long"


def _partial(cid: np.ndarray, d2: np.ndarray, x: np.ndarray, k: int, tests: int) -> pa.RecordBatch:
    n = np.bincount(cid, minlength=k)
    sums = np.array([np.bincount(cid, x[:, i], k) for i in range(x.shape[1])]).T
    sse = np.bincount(cid, d2, k)
    used = np.flatnonzero(n)
    share = np.zeros(len(used), dtype=np.int64)
    share[0] = tests
    return pa.RecordBatch.from_arrays([pa.array(used.astype(np.int32)), pa.array(n[used]), pa.array(sums[used].tolist(), pa.list_(pa.float64())), pa.array(sse[used]), pa.array(share)], ["cid", "n", "sums", "sse", "point_tests"])


def _lloyd_kernel(shared, index: bool):
    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        centroids = shared.value
        k, d = centroids.shape
        ids = np.arange(k)
        root = tree.build(centroids, ids, tree.Params(c=4, t=3, mode="sort")) if index else None
        for batch in batches:
            if not batch.num_rows:
                continue
            x = as_matrix(batch.column(0), d)
            if root is None:
                cid, d2 = nearest(x, centroids)
                tests = len(x) * k
            else:
                cid, d2, tests = np.empty(len(x), np.int64), np.empty(len(x)), 0
                for i, q in enumerate(x):
                    found, work = tree.knn(root, centroids, ids, q, 1)
                    cid[i], tests = found[0][1], tests + work.points_accessed
                    gap = q - centroids[cid[i]]
                    d2[i] = (gap * gap).sum()
            yield _partial(cid, d2, x, k, tests)

    return kernel


def _filter_kernel(shared):
    """Leaves: where one centroid is nearer than all others from anywhere in the box, the whole node goes to it."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        centroids = shared.value
        k, d = centroids.shape
        for batch in batches:
            for packed in batch.column(0):
                root, points, _ = tree.unpack(packed.as_py())
                tests, cids, places = 0, [], []
                line = [(root, np.arange(k))]
                while line:
                    node, left = line.pop()
                    if not node.n:
                        continue
                    low = np.array([np.sqrt((np.maximum(np.maximum(node.lo - c, c - node.hi), 0) ** 2).sum()) for c in centroids[left]])
                    high = np.array([np.sqrt((np.maximum(np.abs(c - node.lo), np.abs(c - node.hi)) ** 2).sum()) for c in centroids[left]])
                    left = left[low <= high.min() * (1 + 1e-12)]
                    if len(left) == 1 or node.idx is not None:
                        mine = node.idx if node.idx is not None else np.concatenate([x.idx for x in tree.leaves(node)])
                        if len(left) > 1:
                            at, _ = nearest(points[mine], centroids[left])
                            tests += len(mine) * len(left)
                        else:
                            at = np.zeros(len(mine), dtype=np.int64)
                        cids.append(left[at])
                        places.append(mine)
                    else:
                        line.extend((kid, left) for kid in node.kids)
                if places:
                    cid, mine = np.concatenate(cids), np.concatenate(places)
                    gap = points[mine] - centroids[cid]
                    yield _partial(cid, (gap * gap).sum(1), points[mine], k, tests)

    return kernel


def step(source: DataFrame | IndexHandle, centroids: np.ndarray, mode: str = "lloyd") -> tuple[np.ndarray, np.ndarray, float, int]:
    """(new centroids, sizes, sse before moving, distance tests); each task sends k sums, added up in Spark."""
    if len(centroids) > MAX_CENTROIDS:
        raise ValueError("more centroids than go to every task")
    if mode == "node_filter":
        frame = source.cells.select("packed")
    else:
        frame = (source.points() if isinstance(source, IndexHandle) else source).select("coords")
    ship(frame.sparkSession)
    shared = frame.sparkSession.sparkContext.broadcast(centroids)
    kernel = _filter_kernel(shared) if mode == "node_filter" else _lloyd_kernel(shared, mode == "centroid_index")
    d = centroids.shape[1]
    sums = [F.sum(F.element_at("sums", i + 1)).alias(f"s{i}") for i in range(d)]
    rows = frame.mapInArrow(kernel, _SUMS).groupBy("cid").agg(F.sum("n").alias("n"), F.sum("sse").alias("sse"), F.sum("point_tests").alias("tests"), *sums).collect()  # k rows
    new, sizes = centroids.copy(), np.zeros(len(centroids), dtype=np.int64)
    for r in rows:
        new[r.cid], sizes[r.cid] = [r[f"s{i}"] / r.n for i in range(d)], r.n
    return new, sizes, float(sum(r.sse for r in rows)), int(sum(r.tests for r in rows))


def run(source: DataFrame | IndexHandle, k: int, iters: int = 10, mode: str = "lloyd", centroids: np.ndarray | None = None, tol: float = 0.0) -> dict:
    """Rounds until nothing moves more than tol; mode: lloyd, centroid_index, node_filter. A centroid without points stays."""
    points = source.points() if isinstance(source, IndexHandle) else source
    at = initial(points, k) if centroids is None else np.array(centroids, dtype=float)
    history = []
    for _ in range(iters):
        new, sizes, sse, tests = step(source, at, mode)
        history.append({"sse": sse, "tests": tests})
        moved = float(np.abs(new - at).max())
        at = new
        if moved <= tol:
            break
    return {"centroids": at, "sizes": sizes, "history": history}


def assigned(points: DataFrame, centroids: np.ndarray) -> DataFrame:
    """(pid, cid): the nearest centroid of every point."""
    ship(points.sparkSession)
    shared = points.sparkSession.sparkContext.broadcast(centroids)

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                cid, _ = nearest(as_matrix(batch.column(1), centroids.shape[1]), shared.value)
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(cid.astype(np.int32))], ["pid", "cid"])

    return points.select(F.col("pid").cast("long").alias("pid"), "coords").mapInArrow(kernel, "pid long, cid int")


def update(source: DataFrame | IndexHandle, previous: dict, iters: int = 3, mode: str = "node_filter") -> dict:
    """After points came: on from the previous centroids."""
    return run(source, len(previous["centroids"]), iters, mode, previous["centroids"])


def simplify(source: DataFrame | IndexHandle, k: int, iters: int = 10, mode: str = "lloyd") -> DataFrame:
    """The data set as k centroids with their counts: (cid, n, coords)."""
    spark = (source.cells if isinstance(source, IndexHandle) else source).sparkSession
    out = run(source, k, iters, mode)
    return spark.createDataFrame([(i, int(n), c.tolist()) for i, (n, c) in enumerate(zip(out["sizes"], out["centroids"], strict=True))], "cid int, n long, coords array<double>")


def mllib(points: DataFrame, k: int, iters: int = 10, seed: int = 1) -> float:
    """The SSE of the library's own k-means, as a control."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector

    return KMeans(k=k, maxIter=iters, seed=seed).fit(points.select(array_to_vector("coords").alias("features"))).summary.trainingCost
