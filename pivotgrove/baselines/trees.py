"""Other indexes with the same cells, search and counters: kinds of tree as builders, a forest, an R-tree, grids."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from pivotgrove.functions.geometry import dist
from pivotgrove.operators import search, tree
from pivotgrove.operators.index import IndexHandle, build_index
from pivotgrove.operators.tree import Node, Params


def base_multiway(points: DataFrame, **options) -> IndexHandle:
    """Equal-count cuts by sorting."""
    return build_index(points, mode="sort", **options)


def equal_width(points: DataFrame, **options) -> IndexHandle:
    """Unbalanced: cuts of equal width."""
    return build_index(points, mode="equal_width", **options)


def binary_kd(points: DataFrame, **options) -> IndexHandle:
    return build_index(points, mode="sort", t=2, **options)


def ball_builder(points: np.ndarray, pids: np.ndarray, p: Params) -> Node:
    """Two far poles by two farthest-point passes; each point goes to the nearer one."""
    root = tree.volume(points, 0)
    line = [(root, np.arange(len(points)))]
    while line:
        node, mine = line.pop()
        x = points[mine]
        if p.is_leaf(len(mine)) or (x == x[0]).all() or node.depth > tree.MAX_DEPTH:
            node.idx = mine
            continue
        a = x[tree.distances(x, x.mean(0)).argmax()]
        b = x[tree.distances(x, a).argmax()]
        side = tree.distances(x, a) > tree.distances(x, b)
        node.dim, node.pivots = 0, np.zeros(1)
        for part in (mine[~side], mine[side]):
            kid = tree.volume(points[part], node.depth + 1)
            node.kids.append(kid)
            line.append((kid, part))
    return root


def ball_tree(points: DataFrame, **options) -> IndexHandle:
    return build_index(points, Params(t=2, **options), builder=ball_builder)


def packed_rtree_builder(points: np.ndarray, pids: np.ndarray, p: Params) -> Node:
    """Sort-tile packing: leaves of c points by slabs of the first coordinate, then runs of the second; packed upwards."""

    def tiles(idx: np.ndarray, dim: int, size: int) -> list[np.ndarray]:
        parts = -(-len(idx) // size)
        if dim == points.shape[1] - 1 or parts <= 1:
            order = idx[np.lexsort((pids[idx], points[idx, dim]))]
            return [order[i : i + size] for i in range(0, len(order), size)] or [order]
        slabs = int(np.ceil(parts ** (1 / (points.shape[1] - dim))))
        step = max(1, -(-len(idx) // slabs))
        order = idx[np.lexsort((pids[idx], points[idx, dim]))]
        return [t for i in range(0, len(order), step) for t in tiles(order[i : i + step], dim + 1, size)]

    level = []
    for part in tiles(np.arange(len(points)), 0, p.c) if len(points) else [np.empty(0, np.int64)]:
        leaf = tree.volume(points[part], 0)
        leaf.idx = part
        level.append((leaf, part))
    fan = max(2, p.t if isinstance(p.t, int) else 8)
    while len(level) > 1:
        upper = []
        for i in range(0, len(level), fan):
            group = level[i : i + fan]
            if len(group) == 1 and upper:
                upper[-1][0].kids.append(group[0][0])
                both = np.concatenate((upper[-1][1], group[0][1]))
                new = tree.volume(points[both], 0)
                new.kids, new.dim, new.pivots = upper[-1][0].kids, 0, np.zeros(len(upper[-1][0].kids) - 1)
                upper[-1] = (new, both)
                continue
            mine = np.concatenate([g[1] for g in group])
            node = tree.volume(points[mine], 0)
            node.kids, node.dim, node.pivots = [g[0] for g in group], 0, np.zeros(len(group) - 1)
            upper.append((node, mine))
        level = upper
    root = level[0][0]
    line = [(root, 0)]
    while line:
        node, depth = line.pop()
        node.depth = depth
        line.extend((k, depth + 1) for k in node.kids)
    return root


def packed_rtree(points: DataFrame, **options) -> IndexHandle:
    return build_index(points, Params(**options), builder=packed_rtree_builder)


@dataclass(frozen=True)
class LearnedRTree:
    """A packed R-tree with a classifier from a query's place to its leaf's cell; its answer bounds the exact search."""

    ix: IndexHandle
    model: object

    def knn(self, queries: DataFrame) -> DataFrame:
        return search.knn(self.ix, queries, "box_dfs", home=self.guessed(queries))

    def guessed(self, queries: DataFrame) -> DataFrame:
        from pyspark.ml.functions import array_to_vector

        told = self.model.transform(queries.withColumn("features", array_to_vector("qcoords"))).select("qid", F.col("prediction").cast("int").alias("label"))
        return told.join(F.broadcast(_places(self.ix)), "label").select("qid", "cell_id")


def _places(ix: IndexHandle) -> DataFrame:
    """(cell_id, label): a row a cell."""
    return ix.summary().select("cell_id", (F.row_number().over(Window.orderBy("cell_id")) - 1).alias("label"))


def learned_rtree(points: DataFrame, sample: int = 20_000, **options) -> LearnedRTree:
    from pyspark.ml.classification import DecisionTreeClassifier
    from pyspark.ml.functions import array_to_vector

    ix = packed_rtree(points, **options)
    places = _places(ix)
    rows = ix.points().select("pid", "coords", "cell_id", F.xxhash64("pid").alias("h")).orderBy("h").limit(sample).join(F.broadcast(places), "cell_id")
    model = DecisionTreeClassifier(maxDepth=10).fit(rows.select(array_to_vector("coords").alias("features"), F.col("label").cast("double").alias("label")))
    return LearnedRTree(ix, model)


@dataclass(frozen=True)
class Forest:
    """Trees of doubling size: a batch becomes a tree and absorbs every smaller one; queries ask all of them."""

    trees: tuple[tuple[int, IndexHandle], ...]  # (points, index)
    params: Params

    def insert(self, batch: DataFrame) -> Forest:
        batch = batch.select("pid", "coords")
        n, kept = batch.count(), []
        for size, ix in sorted(self.trees, key=lambda x: x[0]):
            if size <= 2 * n:
                batch, n = batch.unionByName(ix.points().select("pid", "coords")), n + size
            else:
                kept.append((size, ix))
        return Forest((*kept, (n, build_index(batch, self.params))), self.params)

    def knn(self, queries: DataFrame, strategy: str = "box_dfs") -> DataFrame:
        asked = search.prepared(queries, strategy)
        rows = None
        for _, ix in self.trees:
            one = search.visits(ix, asked, True)
            rows = one if rows is None else rows.unionByName(one)
        return search.top_k(rows, asked)


def forest(points: DataFrame, **options) -> Forest:
    return Forest((), Params(mode="sort", t=2, **options)).insert(points)


# --- space partitions without a tree -----------------------------------------------------------------------------


def grid(points: DataFrame, width: list[float]) -> DataFrame:
    """points with the grid cell of each: an array of floors."""
    return points.withColumn("cell", F.transform(F.arrays_zip("coords", F.array(*[F.lit(float(w)) for w in width]).alias("w")), lambda z: F.floor(z["coords"] / z["w"])))


def grid_radius(points: DataFrame, queries: DataFrame, width: list[float]) -> DataFrame:
    """Radius search by equal cells: each query is copied to the cells its box touches, then an equi-join."""
    asked = queries.select("qid", "qcoords", "r", F.array().cast("array<bigint>").alias("cell"))
    for i, w in enumerate(width):
        x = F.element_at("qcoords", i + 1)
        asked = asked.withColumn("place", F.explode(F.sequence(F.floor((x - F.col("r")) / w), F.floor((x + F.col("r")) / w)))).withColumn("cell", F.array_append("cell", F.col("place"))).drop("place")
    return grid(points, width).join(asked, "cell").withColumn("dist", dist(F.col("coords"), F.col("qcoords"))).where("dist <= r").select("qid", "pid", "dist")


def zorder(points: DataFrame, lo: list[float], width: list[float], bits: int = 16) -> DataFrame:
    """points with the interleaved bits of their grid place: neighbours share prefixes, so a range sort clusters them."""
    code = F.lit(0).cast("long")
    d = len(width)
    for i in range(d):
        place = F.least(F.lit((1 << bits) - 1), F.greatest(F.lit(0), F.floor((F.element_at("coords", i + 1) - lo[i]) / width[i]))).cast("long")
        for b in range(bits):
            code = code.bitwiseOR(F.shiftleft(F.shiftright(place, b).bitwiseAND(F.lit(1)), b * d + i))
    return points.withColumn("z", code)


