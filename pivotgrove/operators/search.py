"""Exact search over the index: kNN, radius, kNN join, by any of the four strategies or one for each query.

A query meets only the cells that can hold an answer. For kNN a first bound needs no point: cells in order of
their farthest possible distance, until they hold k points together; then the same among the marks (boxes of some
hundred points) of the query's nearest cell. Queries are then dealt to cells (points
never move), the kernel walks the cell's tree, and k rows a cell and query come back to one window.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from pivotgrove.functions import geometry as G
from pivotgrove.operators import tree
from pivotgrove.operators.index import IndexHandle, as_matrix
from pivotgrove.runtime import giving_back, materialise, ship

MAX_SUMMARY_CELLS = 200_000  #: cell bounds that go to every task (about 100 bytes each); beyond, a plain join
MAX_MARKS = 4_000_000  #: numbers of the marks that go to every task; beyond, the cells' bound alone
QUERY_BLOCK = 2048
ROUTED, ROUTED_NUMBERS = 8192, 250_000  #: queries, and their distances to cells, that a task routes at once
FINER_NUMBERS = 500_000  #: distances to marks that it looks at together
MAX_OUT_ROWS = 100_000  #: answers that a task holds before it hands them on
TOGETHER, MOST_TOGETHER = 512, 128  #: walks that go through a cell side by side, and the answers each may keep
WAVES = 4  #: tasks for each core where the cells are few
MOVED_POINTS = 4_000_000  #: points of a small index, a copy for each block of queries, that an exchange may move to spread the work
_PROBE = "qid long, qcoords array<double>, k long, r double, strategy string, bound double, cell_id long"

#: Which lemma rules a node out: (operation, volume) -> test.
PRUNING = {("knn", "box"): "box lower bound beyond the k-th distance", ("knn", "ball"): "ball lower bound beyond the k-th distance", ("radius", "box"): "box lower bound beyond the radius", ("radius", "ball"): "centres farther apart than both radii"}


def _reach(high: np.ndarray, n: np.ndarray, k: np.ndarray) -> np.ndarray:
    """The farthest distance within which boxes of n points hold k together; infinite where all hold less."""
    if high.shape[1] > 64:  # k points are in the k nearest-ended boxes at most
        most = min(high.shape[1], max(int(k.max()), 1))
        near = np.argpartition(high, most - 1, axis=1)[:, :most]
        high, n = np.take_along_axis(high, near, 1), n[near] if n.ndim == 1 else np.take_along_axis(n, near, 1)
    else:
        n = np.broadcast_to(n, high.shape)
    order = np.argsort(high, axis=1)
    held = np.cumsum(np.take_along_axis(n, order, 1), axis=1)
    at = np.minimum((held < k[:, None]).sum(1), high.shape[1] - 1)
    return np.where(held[:, -1] >= k, np.take_along_axis(high, np.take_along_axis(order, at[:, None], 1), 1)[:, 0], np.inf)


def _finer(bound: np.ndarray, home: np.ndarray, marks: tuple[np.ndarray, np.ndarray, np.ndarray], q: np.ndarray, k: np.ndarray) -> np.ndarray:
    """bound, or what the marks of the home cell come to where that is less; queries whose homes have about as many marks are looked at together.

    marks: those of all cells one after the other, and where each cell's begin and how many they are.
    """
    held, begin, many = marks
    out, d = bound.copy(), q.shape[1]
    order = np.argsort(many[home], kind="stable")
    sizes, start = many[home[order]], int((many[home] == 0).sum())
    while start < len(order):
        end = min(start + max(1, FINER_NUMBERS // (2 * int(sizes[start]))), int(np.searchsorted(sizes, 2 * sizes[start], side="right")))
        mine, width = order[start:end], np.arange(sizes[end - 1])
        real = width < sizes[start:end, None]
        at = np.where(real, begin[home[mine]][:, None] + width, 0)
        far = np.zeros(at.shape)
        for i in range(d):
            x = q[mine, i][:, None]
            far += np.maximum(np.abs(x - held[at, 1 + i]), np.abs(x - held[at, 1 + d + i])) ** 2
        out[mine] = np.minimum(out[mine], _reach(np.where(real, np.sqrt(far), np.inf), np.where(real, held[at, 0], 0), k[mine]))
        start = end
    return out


def _route(shared, knn: bool, d: int):
    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cell, n, lo, hi, centre, radius, marks = shared.value
        for batch in batches:
            step = max(1, min(ROUTED, ROUTED_NUMBERS // max(len(cell), 1)))
            for start in range(0, batch.num_rows, step):
                rows = batch.slice(start, step)
                q = as_matrix(rows.column(1), d)
                low, high = np.zeros((len(q), len(cell))), np.zeros((len(q), len(cell)))
                for i in range(d):
                    x = q[:, i][:, None]
                    under, over = lo[:, i][None, :] - x, x - hi[:, i][None, :]  # one of them is no more than 0, and its size that of the farther side
                    low += np.maximum(np.maximum(under, over), 0) ** 2
                    high += np.minimum(under, over) ** 2
                low, high = np.sqrt(low), np.sqrt(high)
                home = np.argmin(low + 1e-6 * high, axis=1)
                is_ball = np.flatnonzero(np.asarray(pc.starts_with(rows.column(4), "ball").to_numpy(zero_copy_only=False), dtype=bool))
                if len(is_ball):
                    ball = np.zeros((len(is_ball), len(cell)))
                    for i in range(d):
                        ball += (q[is_ball, i][:, None] - centre[:, i][None, :]) ** 2
                    low[is_ball] = np.maximum(np.sqrt(ball) - radius[None, :] * (1 + 1e-12), 0)
                if knn:
                    k = np.asarray(rows.column(2))
                    bound = _reach(high, n, k)
                    if marks is not None:
                        bound = _finer(bound, home, marks, q, k)
                else:
                    bound = np.asarray(rows.column(3))
                at, to = np.nonzero(low <= bound[:, None] * (1 + 1e-9))
                yield pa.RecordBatch.from_arrays([*[rows.column(c).take(pa.array(at)) for c in range(5)], pa.array(bound[at]), pa.array(cell[to])], ["qid", "qcoords", "k", "r", "strategy", "bound", "cell_id"])

    return kernel


def probes(ix: IndexHandle, queries: DataFrame, knn: bool) -> DataFrame:
    """(query, bound, cell_id) for every cell that can hold an answer."""
    spark = queries.sparkSession
    plain = queries.select("qid", "qcoords", "k", "r", "strategy")
    summary = ix.summary()
    cells, _, numbers = ix.totals()
    if cells <= MAX_SUMMARY_CELLS:
        marked = knn and numbers is not None and numbers <= MAX_MARKS
        got = (ix.cells.select(*summary.columns, "marks") if marked else summary).toArrow()
        if not got.num_rows:
            return spark.createDataFrame([], _PROBE)
        marks = None
        if marked:
            each = [np.asarray(m.values if m.is_valid else [], dtype=np.float64).reshape(-1, 2 * ix.d + 1) for m in got["marks"]]
            many = np.array([len(m) for m in each])
            marks = np.concatenate(each), np.cumsum(many) - many, many
        shared = spark.sparkContext.broadcast((got["cell_id"].to_numpy(), got["n_points"].to_numpy(), *(as_matrix(got[c], ix.d) for c in ("lo", "hi", "center")), got["radius"].to_numpy(), marks))
        return plain.mapInArrow(_route(shared, knn, ix.d), _PROBE)
    q = F.col("qcoords")
    pairs = plain.crossJoin(summary)
    if knn:
        reach = pairs.withColumn("far", G.box_upper_bound(F.col("lo"), F.col("hi"), q))
        held = F.sum("n_points").over(Window.partitionBy("qid").orderBy("far", "cell_id"))
        bound = reach.withColumn("held", held).groupBy("qid").agg(F.min(F.when(F.col("held") >= F.col("k"), F.col("far"))).alias("bound"))
        pairs = pairs.join(bound, "qid").withColumn("bound", F.coalesce("bound", F.lit(float("inf"))))
    else:
        pairs = pairs.withColumn("bound", F.col("r"))
    return pairs.where(G.box_lower_bound(F.col("lo"), F.col("hi"), q) <= F.col("bound") * (1 + 1e-9)).select("qid", "qcoords", "k", "r", "strategy", "bound", "cell_id")


_OUT = "qid long, pid long, dist double, strategy string, nodes_visited long, leaves_visited long, points_accessed long, pruned_nodes long, elapsed_us long"
_NONE = np.empty(0)


def _out(only: str) -> str:
    return ", ".join(_OUT.split(", ")[:3]) if only == "answers" else _OUT


def _walks(packed: bytes, wanted: pa.StructArray, d: int, child_order: str, seed_bound: bool, dfs_bound: str) -> Iterator[tuple]:
    """The kNN visits of one cell, many walks at a time; the time of each is its share. Where all points may be asked for, one by one."""
    import time

    flat, whole, lone = tree.Flat.of(packed), None, None
    points = flat.n[0]
    qid, k, strategy = wanted.field("qid").to_numpy(), wanted.field("k").to_numpy(), np.array(wanted.field("strategy").to_pylist())
    q, bound = as_matrix(wanted.field("qcoords"), d), wanted.field("bound").to_numpy() if seed_bound else np.full(len(qid), np.inf)
    budget = None
    if wanted.type.get_field_index("budget") >= 0:
        budget = wanted.field("budget").fill_null(np.iinfo(np.int64).max).to_numpy()
    alone = (k > MOST_TOGETHER) | (k >= points)
    for i in np.flatnonzero(alone).tolist():
        how = q[i], int(k[i]), strategy[i], child_order, bound[i], None if budget is None else int(budget[i]), dfs_bound
        if on_arrays := k[i] < points or budget is None:
            lone = lone or tree.Lone(packed)
        else:
            whole = whole or tree.unpack(packed)
        began = time.perf_counter_ns()
        near, far, work = lone.nearest(*how) if on_arrays else tree.nearest(*whole, *how)
        yield int(qid[i]), near, far, strategy[i], work.nodes_visited, work.leaves_visited, work.points_accessed, work.pruned_nodes, (time.perf_counter_ns() - began) // 1000
    step = max(32, min(TOGETHER, 2_000_000 // len(flat.n)))
    for s in np.unique(strategy[~alone]):
        mine = np.flatnonzero(~alone & (strategy == s))
        for some in np.split(mine, range(step, len(mine), step)):
            began = time.perf_counter_ns()
            found, work = tree.nearest_together(flat, q[some], k[some], bound[some], s, child_order, None if budget is None else budget[some], dfs_bound)
            took = (time.perf_counter_ns() - began) // 1000 // len(some)
            for i, (near, far), w in zip(qid[some].tolist(), found, work.tolist(), strict=True):
                yield i, near, far, s, *w, took


def _visit(knn: bool, child_order: str, accept_inside: bool, d: int, seed_bound: bool = True, dfs_bound: str = "own", timed: bool = False, only: str = ""):
    """One row an answer, and for each query and cell one row of counters (pid null); at most MAX_OUT_ROWS and one visit's are held.

    timed: every walk goes alone, so that elapsed_us is its own. only: "answers" (without the columns of counters)
    or "log" (the rows of counters), where nothing else is read of the same walks.
    """
    names = [x.split()[0] for x in _out(only).split(", ")]

    def batch_of(visits: list[tuple]) -> pa.RecordBatch:
        sizes = [len(v[1]) for v in visits]
        if only == "answers":
            near, far = [np.concatenate([v[c] for v in visits]) if len(visits) > 1 else visits[0][c] for c in (1, 2)]
            return pa.RecordBatch.from_arrays([pa.array(np.repeat(np.array([v[0] for v in visits], dtype=np.int64), sizes)), pa.array(near, pa.int64()), pa.array(far, pa.float64())], names)
        qid = np.array([v[0] for v in visits], dtype=np.int64)
        kind = pa.array([v[3] for v in visits])
        total, counters = sum(sizes), [pa.array([v[c] for v in visits], pa.int64()) for c in range(4, 9)]
        columns = [
            pa.array(np.concatenate((np.repeat(qid, sizes), qid))),
            pa.concat_arrays([pa.array(np.concatenate([v[1] for v in visits]), pa.int64()), pa.nulls(len(visits), pa.int64())]),
            pa.concat_arrays([pa.array(np.concatenate([v[2] for v in visits]), pa.float64()), pa.nulls(len(visits), pa.float64())]),
            pa.concat_arrays([kind.take(pa.array(np.repeat(np.arange(len(visits)), sizes))), kind]),
            *[pa.concat_arrays([pa.nulls(total, pa.int64()), c]) for c in counters],
        ]
        return pa.RecordBatch.from_arrays(columns, names)

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import time

        def one_by_one(at: int, batch: pa.RecordBatch) -> Iterator[tuple]:
            nonlocal last, held, lone
            cell = batch.column(2)[at].as_py()
            if cell != last:  # the blocks of a cell follow one another
                last, held, lone = cell, None, tree.Lone(batch.column(0)[at].as_py())
            for w in batch.column(1)[at].as_py():
                q, strategy = np.array(w["qcoords"]), w["strategy"]
                alone = w.get("budget") is None or knn and w["k"] < lone.flat.n[0]
                if held is None and not alone:
                    held = tree.unpack(batch.column(0)[at].as_py())
                how = q, w["k"], strategy, child_order, w["bound"] if seed_bound else np.inf, w.get("budget"), dfs_bound
                began = time.perf_counter_ns()
                if knn:
                    near, far, work = lone.nearest(*how) if alone else tree.nearest(*held, *how)
                elif alone:
                    near, far, work = lone.within(q, w["r"], strategy, accept_inside)
                else:
                    near, far, work = tree.radius_search(*held, q, w["r"], strategy, accept_inside, w.get("budget"))
                took = (time.perf_counter_ns() - began) // 1000
                yield w["qid"], near, far, strategy, work.nodes_visited, work.leaves_visited, work.points_accessed, work.pruned_nodes, took

        last = held = lone = None
        for batch in batches:
            for at in range(batch.num_rows):
                if knn and not timed:
                    visited = _walks(batch.column(0)[at].as_py(), batch.column(1)[at].values, d, child_order, seed_bound, dfs_bound)
                else:
                    visited = one_by_one(at, batch)
                done, many = [], 0
                for visit in visited:
                    if only == "log":
                        visit = (visit[0], _NONE, _NONE, *visit[3:])
                    done.append(visit)
                    many += len(visit[1]) + 1
                    if many >= MAX_OUT_ROWS:
                        yield batch_of(done)
                        done, many = [], 0
                if done:
                    yield batch_of(done)

    return giving_back(kernel)


def prepared(queries: DataFrame, strategy: str | None) -> DataFrame:
    """Fill in what a query frame may lack: k, r and the strategy."""
    have = set(queries.columns)
    out = queries.withColumn("qcoords", F.col("qcoords").cast("array<double>"))
    out = out.withColumn("k", (F.col("k") if "k" in have else F.lit(0)).cast("long")).withColumn("r", (F.col("r") if "r" in have else F.lit(None)).cast("double"))
    if strategy or "strategy" not in have:
        out = out.withColumn("strategy", F.lit(strategy or "box_dfs"))
    return out


def visits(ix: IndexHandle, queries: DataFrame, knn: bool, child_order: str = "nearest", accept_inside: bool = False, **how) -> DataFrame:
    """Every (query, cell) visit."""
    ship(queries.sparkSession)
    return at_cells(ix, probes(ix, queries, knn), queries.count(), knn, child_order, accept_inside, **how)


def at_cells(ix: IndexHandle, asked: DataFrame, queries: int, knn: bool, child_order: str, accept_inside: bool, block: int = QUERY_BLOCK, **how) -> DataFrame:
    """The visits of asked: a cell's queries travel in blocks of about so many, so that a favourite cell is many tasks.

    Where the cells are few and small, they and their blocks are dealt to all cores; else points stay where they are.
    """
    spark = asked.sparkSession
    cells, held, _ = ix.totals()
    tasks = WAVES * spark.sparkContext.defaultParallelism
    ways = max(1, min(-(-tasks // max(cells, 1)), -(-queries // 16)))
    spread = bool(cells) and ways * held <= MOVED_POINTS
    ways, size, block = ways if spread else 1, block, F.lit(0)
    if queries > size:  # a cell may have more than a block
        asked = materialise(asked, "probes")
        crowded = asked.groupBy("cell_id").agg(F.ceil(F.count("*") / size).alias("blocks")).where("blocks > 1")
        asked = asked.join(F.broadcast(crowded) if cells <= MAX_SUMMARY_CELLS else crowded, "cell_id", "left")
        block = F.pmod(F.xxhash64("qid"), F.greatest(F.coalesce("blocks", F.lit(1)), F.lit(ways)))
    elif ways > 1:
        block = F.pmod(F.xxhash64("qid"), F.lit(ways))
    more = ["budget"] if "budget" in asked.columns else []
    blocks = asked.groupBy("cell_id", block.alias("block")).agg(F.collect_list(F.struct("qid", "qcoords", "k", "r", "strategy", "bound", *more)).alias("asked"))
    met = blocks.join(ix.cells.select("cell_id", "packed"), "cell_id").select("packed", "asked", "cell_id")
    return (met.repartition(tasks) if spread else met).mapInArrow(_visit(knn, child_order, accept_inside, ix.d, **how), _out(how.get("only", "")))


def top_k(rows: DataFrame, queries: DataFrame) -> DataFrame:
    best = Window.partitionBy("qid").orderBy("dist", "pid")
    return rows.where("pid is not null").select("qid", "pid", "dist").withColumn("rank", F.row_number().over(best)).join(queries.select("qid", "k"), "qid").where("rank <= k").select("qid", "pid", "rank", "dist")


def knn(ix: IndexHandle, queries: DataFrame, strategy: str | None = None, child_order: str = "nearest", home_pass: bool = False, home: DataFrame | None = None, **how) -> DataFrame:
    """(qid, pid, rank, dist): the k nearest by (dist, pid); all points where k is larger, none for k below 1.

    home_pass visits each query's nearest cell first, or the one that home (qid, cell_id) names, and goes on with
    the distance found there (depth first over cells); otherwise one wave visits all candidate cells (breadth first). seed_bound=False: a tree's walk begins without
    the bound that cells gave; dfs_bound="single": depth first prunes by boxes whatever the volume.
    """
    asked = prepared(queries, strategy).where("k >= 1")
    least, n = asked.agg(F.min("k"), F.count("*")).first()
    least = least or 0
    total = ix.totals()[1] if least > 1000 else 0
    if least > 1000 and least >= total:  # nothing is cut, so no order is needed unless ranks are asked for
        ways = max(1, MOVED_POINTS // max(total, 1))  # copies of each cell that may be dealt to the cores; answers leave as they are told, so a block may have many
        rows = visits(ix, asked, True, child_order, block=max(QUERY_BLOCK, -(-n // ways)), only="answers", **how)
        return rows.select("qid", "pid", F.row_number().over(Window.partitionBy("qid").orderBy("dist", "pid")).alias("rank"), "dist")
    if not home_pass and home is None:
        return top_k(visits(ix, asked, True, child_order, only="answers", **how), asked)
    ship(queries.sparkSession)
    asked = materialise(asked, "queries")
    candidates = materialise(probes(ix, asked, True), "probes")
    near = candidates.join(ix.summary().select("cell_id", "lo", "hi"), "cell_id").withColumn("low", G.box_lower_bound(F.col("lo"), F.col("hi"), F.col("qcoords")))
    nearest = near.groupBy("qid").agg(F.min_by("cell_id", F.struct("low", "cell_id")).alias("cell_id"))
    if home is not None:  # a guess outside the candidates can hold no answer: the nearest cell stands in
        guess = candidates.select("qid", "cell_id").join(home.select("qid", "cell_id"), ["qid", "cell_id"], "left_semi").withColumnRenamed("cell_id", "guess")
        nearest = nearest.join(guess, "qid", "left").select("qid", F.coalesce("guess", "cell_id").alias("cell_id"))
    nearest = materialise(nearest, "homes")
    first = materialise(at_cells(ix, candidates.join(nearest, ["qid", "cell_id"]), n, True, child_order, False, only="answers", **how), "home-pass")
    kth = first.where("pid is not null").groupBy("qid").agg(F.count("*").alias("got"), F.max("dist").alias("kth"))
    rest = near.join(nearest.withColumnRenamed("cell_id", "home"), "qid").where("cell_id != home").join(kth, "qid", "left")
    bound = F.when(F.col("got") >= F.col("k"), F.least("bound", "kth")).otherwise(F.col("bound"))
    rest = rest.withColumn("bound", bound).where(F.col("low") <= F.col("bound") * (1 + 1e-9)).select("qid", "qcoords", "k", "r", "strategy", "bound", "cell_id")
    return top_k(first.unionByName(at_cells(ix, rest, n, True, child_order, False, only="answers", **how)), asked)


def radius(ix: IndexHandle, queries: DataFrame, strategy: str | None = None, accept_inside: bool = False) -> DataFrame:
    """(qid, pid, dist) of all points within r, the rim included; one exchange, of queries."""
    return visits(ix, prepared(queries, strategy).where("r >= 0"), False, accept_inside=accept_inside, only="answers").select("qid", "pid", "dist")


def access_log(ix: IndexHandle, queries: DataFrame, operation: str = "knn", strategy: str | None = None, child_order: str = "nearest", timed: bool = True) -> DataFrame:
    """(qid, strategy, nodes_visited, leaves_visited, points_accessed, pruned_nodes, elapsed_us) summed over cells.

    timed=False: walks go side by side, which leaves all but elapsed_us as it is.
    """
    rows = visits(ix, prepared(queries, strategy), operation == "knn", child_order, timed=timed, only="log")
    names = ["nodes_visited", "leaves_visited", "points_accessed", "pruned_nodes", "elapsed_us"]
    return rows.groupBy("qid", "strategy").agg(*[F.sum(c).alias(c) for c in names])


def knn_join(ix: IndexHandle, points: DataFrame, k: int, strategy: str = "box_dfs") -> DataFrame:
    """The k nearest indexed points of every row of points."""
    return knn(ix, points.select(F.col("pid").alias("qid"), F.col("coords").alias("qcoords"), F.lit(k).alias("k")), strategy)


def distance_join(ix: IndexHandle, points: DataFrame, r: float) -> DataFrame:
    return radius(ix, points.select(F.col("pid").alias("qid"), F.col("coords").alias("qcoords"), F.lit(r).alias("r")))


def explain_search(ix: IndexHandle, queries: DataFrame, operation: str = "knn", strategy: str = "box_dfs") -> DataFrame:
    """Which cells each query would visit, with the bound and the test that ruled the others out."""
    asked = probes(ix, prepared(queries, strategy), operation == "knn")
    total = ix.summary().count()
    rule = PRUNING[operation, strategy.split("_")[0]]
    return asked.groupBy("qid").agg(F.first("bound").alias("bound"), F.count("*").alias("cells_visited"), F.collect_list("cell_id").alias("cells")).withColumn("cells_pruned", F.lit(total) - F.col("cells_visited")).withColumn("rule", F.lit(rule))
