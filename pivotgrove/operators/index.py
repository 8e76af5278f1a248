"""The two-tier index: cells cut on a bounded sample, a tree in each, one row per cell in the store.

The upper tier is the same multi-way tree, built on a sample that grows with the number of cells up to
MAX_CELLS; as arrays it goes to every task, which deals its points level by level, before the build's only full
exchange. A cell that is still over its size is dealt further by a grid over its two widest coordinates, or,
where its points are equal, by a hash of the id: cells may overlap, their bounds stay true, so answers do too.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field, replace

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pivotgrove.operators import tree
from pivotgrove.operators.tree import Node, Params
from pivotgrove.runtime import give_back, giving_back, materialise, ship

SAMPLE_ROWS, CELL_SAMPLE = 100_000, 64  #: points that the upper tier is cut on: so many, or so many for each cell
MAX_CELLS = 65_536  #: cells of the upper tier; a cell that then holds too much is dealt on by a grid
CELL_POINTS = 65_536  #: points that a cell should hold
FAN = 8
CELL_SCHEMA = "cell_id long, n_points long, lo array<double>, hi array<double>, center array<double>, radius double, marks array<double>, packed binary, version long"
MARK_POINTS = 256  #: a mark is the highest node of a cell's tree with so many points at most
_SUB = 1 << 20


@dataclass(frozen=True)
class IndexHandle:
    """cells: one row a cell, its tree and points packed; upper: the upper tier; version and log of what was done."""

    cells: DataFrame
    upper: Node
    params: Params
    d: int
    version: int = 0
    subs: dict[int, int | list] = field(default_factory=dict)  # a cell dealt on: ways by hash, or [side, then dim, lo, hi of each grid coordinate]
    log: DataFrame | None = None  # every rebuild of every batch

    def nodes(self) -> DataFrame:
        """(cell_id, node_id, parent_id, level, ordinal, split_dim, pivots, is_leaf, n_points, lo, hi, center, radius, path)."""
        schema = "cell_id long, node_id long, parent_id long, level int, ordinal int, split_dim int, pivots array<double>, is_leaf boolean, n_points long, lo array<double>, hi array<double>, center array<double>, radius double, path array<int>"
        return self.cells.select("cell_id", "packed").mapInArrow(_node_rows, schema)

    def points(self) -> DataFrame:
        """(pid, coords, cell_id, leaf_id, path) of every indexed point."""
        return self.cells.select("cell_id", "packed").mapInArrow(_point_rows, "pid long, coords array<double>, cell_id long, leaf_id long, path array<int>")

    def summary(self) -> DataFrame:
        return self.cells.select("cell_id", "n_points", "lo", "hi", "center", "radius")

    def totals(self) -> tuple[int, int, int | None]:
        """(cells, points, numbers of the marks, None where the store has none): one job, the first time."""
        if "_totals" not in self.__dict__:
            marked = "marks" in self.cells.columns
            r = self.cells.agg(F.count("*"), F.sum("n_points"), F.sum(F.size("marks")) if marked else F.lit(0)).first()
            object.__setattr__(self, "_totals", (r[0], r[1] or 0, (r[2] or 0) if marked else None))
        return self._totals

    def stats(self) -> DataFrame:
        """Height, leaves, occupancy, path length, balance: one row."""
        n = self.nodes()
        leaf = F.col("is_leaf")
        return n.agg(
            F.max("level").alias("height"), F.count_if(leaf).alias("leaves"), F.sum(F.when(leaf, F.col("n_points"))).alias("points"),
            F.avg(F.when(leaf, F.col("n_points"))).alias("leaf_fill"), F.max(F.when(leaf, F.col("n_points"))).alias("leaf_most"), F.countDistinct("cell_id").alias("cells"),
        )


def _node_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for cell, packed in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
            root, _, _ = tree.unpack(packed.as_py())
            nodes = tree.preorder(root)
            paths: list[list[int]] = []
            rows = []
            for i, (x, parent, ordinal) in enumerate(nodes):
                paths.append([] if parent < 0 else [*paths[parent], ordinal])
                rows.append((cell, i, parent, x.depth, ordinal, x.dim, None if x.pivots is None else x.pivots.tolist(), x.idx is not None, x.n, x.lo.tolist(), x.hi.tolist(), x.center.tolist(), x.radius, paths[i]))
            doubles, ints = pa.list_(pa.float64()), pa.list_(pa.int32())
            kinds = [pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.int32(), doubles, pa.bool_(), pa.int64(), doubles, doubles, doubles, pa.float64(), ints]
            names = ["cell_id", "node_id", "parent_id", "level", "ordinal", "split_dim", "pivots", "is_leaf", "n_points", "lo", "hi", "center", "radius", "path"]
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], names)


def _point_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for cell, packed in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
            root, points, pids = tree.unpack(packed.as_py())
            paths: list[list[int]] = []
            for i, (x, parent, ordinal) in enumerate(tree.preorder(root)):
                paths.append([] if parent < 0 else [*paths[parent], ordinal])
                if x.idx is not None and len(x.idx):
                    m = len(x.idx)
                    yield pa.RecordBatch.from_arrays(
                        [pa.array(pids[x.idx]), pa.array(points[x.idx].tolist(), pa.list_(pa.float64())), pa.array([cell] * m, pa.int64()), pa.array([i] * m, pa.int64()), pa.array([paths[i]] * m, pa.list_(pa.int32()))],
                        ["pid", "coords", "cell_id", "leaf_id", "path"],
                    )


def _mixed(pids: np.ndarray) -> np.ndarray:
    x = pids.astype(np.int64).view(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    return (x ^ (x >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93) >> np.uint64(20)


def cell_ids(router: tree.Router, subs: dict[int, int | list], points: np.ndarray, pids: np.ndarray) -> np.ndarray:
    cell = router.cells(points)
    out = cell * _SUB
    for big in np.intersect1d(np.unique(cell), np.array(list(subs), dtype=np.int64)).tolist():
        at, how = np.flatnonzero(cell == big), subs[big]
        if isinstance(how, int):
            out[at] += (_mixed(pids[at]) % np.uint64(max(how, 1))).astype(np.int64)
            continue
        side, place = how[0], np.zeros(len(at), dtype=np.int64)
        for dim, lo, hi in (how[1:4], how[4:7])[: 1 if len(how) < 7 else 2]:
            place = place * side + np.clip(((points[at, int(dim)] - lo) / (hi - lo) * side).astype(np.int64), 0, side - 1)
        out[at] += place
    return out


def sound(batch: pa.RecordBatch) -> pa.RecordBatch:
    """The rows of (pid, coords, ...) that validate() calls good: told here, each row's coordinates are computed once."""
    ids, coords = batch.column(0), batch.column(1)
    flat = coords.flatten()  # a null array holds nothing
    finite = np.isfinite(np.asarray(flat.fill_null(np.nan) if flat.null_count else flat, dtype=np.float64))
    if not ids.null_count and not coords.null_count and finite.all():
        return batch
    held = np.asarray(pc.fill_null(pc.list_value_length(coords), 0), dtype=np.int64)
    good = np.asarray(pc.and_(pc.is_valid(ids), pc.is_valid(coords)).to_numpy(zero_copy_only=False), dtype=bool)
    good[np.repeat(np.arange(len(held)), held)[~finite]] = False
    return batch.filter(pa.array(good))


def counted(rows: DataFrame, below: int) -> tuple[int, int, np.ndarray, np.ndarray]:
    """(points, their dimensions, ids and points of the sample) of (pid, coords, draw): one pass counts, and keeps the points drawn below a number."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n = d = 0
        for batch in batches:
            batch = sound(batch)
            if batch.num_rows:
                n, d = n + batch.num_rows, max(d, pc.max(pc.list_value_length(batch.column(1))).as_py())
                some = batch.filter(pc.less(batch.column(2), below))
                if some.num_rows:
                    none = pa.nulls(some.num_rows, pa.int64())
                    yield pa.RecordBatch.from_arrays([none, none, some.column(0), some.column(1)], names)
        yield pa.RecordBatch.from_arrays([pa.array([n]), pa.array([d]), pa.nulls(1, pa.int64()), pa.nulls(1, pa.list_(pa.float64()))], names)

    names = ["n", "d", "pid", "coords"]
    got = rows.mapInArrow(giving_back(kernel), "n long, d long, pid long, coords array<double>").toArrow()
    n, d = pc.sum(got["n"]).as_py() or 0, pc.max(got["d"]).as_py() or 0
    some = got.filter(pc.is_valid(got["pid"]))
    ids = some["pid"].to_numpy()
    order = np.argsort(ids, kind="stable")
    return n, d, ids[order], as_matrix(some["coords"], d)[order] if len(ids) else np.empty((0, d))


def cell_ends(rows: DataFrame, upper: Node, d: int) -> DataFrame:
    """(cell, held, lo, hi) of the cells of the upper tier: each task hands on one row a cell."""
    shared = rows.sparkSession.sparkContext.broadcast(tree.Router.of(upper))
    sides = [f"{end}{i}" for end in "lh" for i in range(d)]

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        router = shared.value
        cells = int(router.leaf.max()) + 1
        held, lo, hi = np.zeros(cells, np.int64), np.full((cells, d), np.inf), np.full((cells, d), -np.inf)
        for batch in batches:
            batch = sound(batch)
            if batch.num_rows:
                points = as_matrix(batch.column(1), d)
                cell = router.cells(points)
                order = np.argsort(cell, kind="stable")
                cell, points = cell[order], points[order]
                first = np.flatnonzero(np.diff(cell, prepend=-1))
                at = cell[first]
                held[at] += np.diff(first, append=len(cell))
                lo[at] = np.minimum(lo[at], np.minimum.reduceat(points, first, axis=0))
                hi[at] = np.maximum(hi[at], np.maximum.reduceat(points, first, axis=0))
        at = np.flatnonzero(held)
        yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(held[at]), *[pa.array(end[at, i]) for end in (lo, hi) for i in range(d)]], ["cell", "held", *sides])

    parts = rows.select("pid", "coords").mapInArrow(giving_back(kernel), ", ".join(["cell long, held long", *[f"{c} double" for c in sides]]))
    return parts.groupBy("cell").agg(F.sum("held").alias("held"), *[(F.min if c[0] == "l" else F.max)(c).alias(c) for c in sides])


def deal(points: DataFrame, upper: Node, subs: dict[int, int | list], d: int) -> DataFrame:
    """(pid, coords, cell_id): the cell of every row that is a point, without an exchange; the upper tier goes to each task as arrays."""
    shared = points.sparkSession.sparkContext.broadcast((tree.Router.of(upper), subs))

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        router, own = shared.value
        for batch in batches:
            batch = sound(batch)
            if batch.num_rows:
                cell = cell_ids(router, own, as_matrix(batch.column(1), d), batch.column(0).to_numpy())
                yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(cell)], ["pid", "coords", "cell_id"])

    return points.select("pid", "coords").mapInArrow(giving_back(kernel), "pid long, coords array<double>, cell_id long")


def upper_tree(sample: np.ndarray, ids: np.ndarray, cells: int, params: Params) -> Node:
    """A tree of about so many leaves: at each node the levels still to come share the fan-out evenly."""
    draw = np.random.default_rng([params.seed, cells])
    root = tree.volume(sample, 0)
    line = [(root, np.arange(len(sample)), cells)]
    while line:
        node, mine, want = line.pop()
        levels = int(np.ceil(np.log(max(want, 2)) / np.log(FAN) - 1e-9))
        cut = tree.split(sample, ids, mine, node.depth, params, draw, int(np.ceil(want ** (1 / levels) - 1e-9))) if want > 1 and len(mine) > 1 else None
        if cut is None:
            node.idx = mine
            continue
        node.dim, node.pivots, parts = cut
        for part in parts:
            kid = tree.volume(sample[part], node.depth + 1)
            node.kids.append(kid)
            line.append((kid, part, int(np.ceil(want * len(part) / len(mine) - 0.3))))
    return root


def _dealt_on(lo: list[float], hi: list[float], parts: int) -> int | list:
    """How a cell that should be so many is dealt on."""
    span = np.array(hi) - np.array(lo)
    wide = [int(i) for i in np.argsort(-span, kind="stable")[:2] if span[i] > 0 and np.isfinite(span[i])]
    if not wide:
        return parts
    side = int(np.ceil(parts ** (1 / len(wide))))
    return [min(side, 1000), *[v for i in wide for v in (i, float(lo[i]), float(hi[i]))]]


def marks(root: Node) -> list[float]:
    """Points, lower and upper corner of each highest node with MARK_POINTS points at most, one after the other."""
    out, line = [], [root]
    while line:
        node = line.pop()
        if node.idx is None and node.n > MARK_POINTS:
            line.extend(node.kids)
        elif node.n:
            out += [float(node.n), *node.lo.tolist(), *node.hi.tolist()]
    return out


def cell_row(cell: int, root: Node, points: np.ndarray, pids: np.ndarray, version: int) -> dict:
    return {"cell_id": cell, "n_points": root.n, "lo": root.lo.tolist(), "hi": root.hi.tolist(), "center": root.center.tolist(), "radius": root.radius, "marks": marks(root), "packed": tree.pack(root, points, pids), "version": version}


CELL_ARROW = pa.schema([("cell_id", pa.int64()), ("n_points", pa.int64()), ("lo", pa.list_(pa.float64())), ("hi", pa.list_(pa.float64())), ("center", pa.list_(pa.float64())), ("radius", pa.float64()), ("marks", pa.list_(pa.float64())), ("packed", pa.binary()), ("version", pa.int64())])


def as_matrix(column: pa.ChunkedArray | pa.Array, d: int) -> np.ndarray:
    flat = column.combine_chunks().flatten() if isinstance(column, pa.ChunkedArray) else column.flatten()
    return np.asarray(flat, dtype=np.float64).reshape(-1, d)


def _build_cell(params: Params, d: int, version: int, builder=None):
    def kernel(table: pa.Table) -> pa.Table:
        points, pids = as_matrix(table["coords"], d), table["pid"].to_numpy()
        order = np.argsort(pids, kind="stable")  # the same tree whatever the arrival order
        points, pids = points[order], pids[order]
        root = (builder or tree.build)(points, pids, params)
        made = pa.Table.from_pylist([cell_row(table["cell_id"][0].as_py(), root, points, pids, version)], schema=CELL_ARROW)
        give_back()
        return made

    return kernel


def build_index(points: DataFrame, params: Params | None = None, cell_points: int = CELL_POINTS, builder=None, **options) -> IndexHandle:
    """Build over (pid, coords). options are those of Params: c, t, mode, delta, l, kappa, omega, split, ...

    builder(points, pids, params) -> Node takes the place of the multi-way build inside each cell (baselines).
    Rows that are no points are left out; an empty input gives an index of no cells.
    """
    params = params or Params(**options)
    spark = points.sparkSession
    ship(spark)
    rows = points.select(F.col("pid").cast("long").alias("pid"), F.col("coords").cast("array<double>").alias("coords"))
    most = points.count()  # rows that are no points among them; of a table that is read from its footers
    wanted = -(-most // cell_points)
    keep = min(1.0, max(SAMPLE_ROWS, CELL_SAMPLE * min(wanted, MAX_CELLS)) / most) if wanted > 1 else 0
    n, d, ids, sample = counted(rows.withColumn("draw", F.pmod(F.xxhash64("pid", F.lit(params.seed)), F.lit(1_000_000_000))), int(keep * 1_000_000_000))
    if not n:
        return IndexHandle(spark.createDataFrame([], CELL_SCHEMA), tree.build(np.empty((0, 1)), np.empty(0, np.int64), replace(params, t=2)), params, 1)
    if params.t == "auto":
        params = replace(params, t=params.fan(n))
    wanted, subs = -(-n // cell_points), {}
    if wanted == 1:
        sample, ids = np.zeros((1, d)), np.zeros(1, np.int64)
    upper = upper_tree(sample, ids, min(wanted, MAX_CELLS), replace(params, mode="sort" if builder else params.mode))
    if wanted > 1:
        for r in cell_ends(rows, upper, d).where(F.col("held") > 2 * cell_points).collect():  # MAX_CELLS rows at most
            subs[int(r.cell)] = _dealt_on([r[f"l{i}"] for i in range(d)], [r[f"h{i}"] for i in range(d)], -(-r.held // cell_points))
    cells = deal(rows, upper, subs, d).groupBy("cell_id").applyInArrow(_build_cell(params, d, 0, builder), CELL_SCHEMA)
    return IndexHandle(materialise(cells, "index-cells"), upper, params, d, 0, subs)
