"""The multi-way tree of one cell, in numpy: build, search, insert, rebalance, and its packed form.

Spark decides which points share a cell and which queries visit it; inside, the traversal order and the
counters are those of a single tree. Points are referred to by their position in the cell's arrays.
"""

from __future__ import annotations

import heapq
import io
from collections import deque
from dataclasses import dataclass, field

import numpy as np

from pivotgrove.plans import cdf, fanout

MODES = ("sort", "candidate_median", "rank_corrected", "inverse", "sketch", "equal_width")
STRATEGIES = ("box_dfs", "box_bfs", "ball_dfs", "ball_bfs")
MAX_DEPTH = 200


@dataclass
class Params:
    c: int = 30
    t: int | str = "auto"  # a number, "auto" (one for the data set) or "per_node"
    mode: str = "rank_corrected"
    delta: float = 0.01
    l: int = 100  # noqa: E741
    kappa: float = 0.15
    omega: float = 0.9
    sub: str = "extremes"
    split: str = "cycle"  # or "widest", "max_variance"
    stop: str = "le"  # or "lt"
    check: str = "after"  # of an insertion: balance after the batch went down, or at each node before
    objective: str = "printed"
    sample_least: int = 64
    small: int = 1024  # learned cuts of so few points are their order statistics: a model costs more there
    seed: int = 0

    def fan(self, n: int) -> int:
        return self.t if isinstance(self.t, int) else fanout.optimal_fanout(max(n, 1), self.c, objective=self.objective)

    def is_leaf(self, n: int) -> bool:
        return n <= self.c if self.stop == "le" else n < max(self.c, 2)


@dataclass(slots=True)
class Node:
    depth: int
    n: int
    lo: np.ndarray
    hi: np.ndarray
    center: np.ndarray
    radius: float
    dim: int = -1
    pivots: np.ndarray | None = None
    kids: list[Node] = field(default_factory=list)
    idx: np.ndarray | None = None  # a leaf's points
    bounds: tuple | None = None  # the kids' volumes, stacked

    def stack(self) -> tuple:
        if self.bounds is None:
            self.bounds = tuple(np.array([getattr(k, a) for k in self.kids]) for a in ("lo", "hi", "center", "radius"))
        return self.bounds


def distances(points: np.ndarray, q: np.ndarray) -> np.ndarray:
    """Euclidean, squares added in coordinate order."""
    total = np.zeros(len(points))
    for i in range(points.shape[1]):
        gap = points[:, i] - q[i]
        total += gap * gap
    return np.sqrt(total)


def volume(points: np.ndarray, depth: int) -> Node:
    if not len(points):
        d = points.shape[1]
        return Node(depth, 0, np.full(d, np.inf), np.full(d, -np.inf), np.zeros(d), -np.inf)
    centre = points.mean(0)
    return Node(depth, len(points), points.min(0), points.max(0), centre, float(distances(points, centre).max()))


def attach_volumes(root: Node, points: np.ndarray) -> None:
    """Boxes and balls of a whole tree: its points in the order of the leaves, each level's nodes as runs of them."""
    order, levels, line = [], {}, [root]
    places: dict[int, int] = {}
    at = 0
    while line:  # preorder: a node's points begin where the leaves before it end
        node = line.pop()
        places[id(node)] = at
        levels.setdefault(node.depth, []).append(node)
        if node.idx is not None:
            order.append(node.idx)
            at += len(node.idx)
        else:
            line.extend(reversed(node.kids))
    d = points.shape[1]
    x = np.vstack((points[np.concatenate(order)], np.zeros((1, d)))) if at else np.zeros((1, d))
    for nodes in levels.values():
        held = [n for n in nodes if n.n]
        for n in nodes:
            if not n.n:
                n.lo, n.hi, n.center, n.radius = np.full(d, np.inf), np.full(d, -np.inf), np.zeros(d), -np.inf
        if not held:
            continue
        start, count = np.array([places[id(n)] for n in held]), np.array([n.n for n in held])
        runs = np.column_stack((start, start + count)).ravel()
        low, high = np.minimum.reduceat(x, runs)[::2], np.maximum.reduceat(x, runs)[::2]
        centre = np.add.reduceat(x, runs)[::2] / count[:, None]
        first = np.concatenate(([0], np.cumsum(count)[:-1]))
        rows = np.arange(count.sum()) + np.repeat(start - first, count)
        total = np.zeros(len(rows))
        for i in range(d):
            gap = x[rows, i] - np.repeat(centre[:, i], count)
            total += gap * gap
        radius = np.sqrt(np.maximum.reduceat(total, first)).tolist()
        for n, a, b, c, r in zip(held, low, high, centre, radius, strict=True):
            n.lo, n.hi, n.center, n.radius = a, b, c, r


def quantile_sketch(x: np.ndarray, draw: np.random.Generator, width: int = 512) -> tuple[np.ndarray, np.ndarray]:
    """(values ascending, weights): blocks of sorted values keep every other one, each for two, until few are left.

    Sketches of parts merge by concatenation and the same steps.
    """
    values, weights, weight = [], [], 1
    while len(x) > width:
        whole = len(x) // width * width
        values.append(x[whole:])
        weights.append(np.full(len(x) - whole, weight))
        x = np.sort(x[:whole].reshape(-1, width), axis=1)[:, int(draw.integers(2)) :: 2].ravel()
        weight *= 2
    values, weights = np.concatenate([*values, x]), np.concatenate([*weights, np.full(len(x), weight)])
    order = np.argsort(values, kind="stable")
    return values[order], weights[order]


def find_pivots(x: np.ndarray, t: int, p: Params, draw: np.random.Generator) -> np.ndarray:
    """The t - 1 cut values of one coordinate: a value equal to a cut goes left."""
    n = len(x)
    at = np.arange(1, t) / t
    ranks = np.maximum(np.ceil(at * n).astype(np.int64) - 1, 0)  # zero-based places of the wanted order statistics
    if p.mode == "equal_width":
        return x.min() + (x.max() - x.min()) * at
    if p.mode == "sketch":
        values, weights = quantile_sketch(x, draw)
        return values[np.minimum(np.searchsorted(np.cumsum(weights), ranks, side="right"), len(values) - 1)]
    if n <= p.small and p.mode != "candidate_median":
        return np.partition(x, ranks)[ranks]
    size = min(n, max(int(p.delta * n), p.sample_least))
    model = cdf.fit(x if size == n else x[draw.integers(0, n, size)], p.l, p.sub)
    if p.mode == "inverse":
        return np.maximum.accumulate([model.inverse(q) for q in at])
    f = model.predict(x)
    if p.mode == "rank_corrected" and p.sub == "extremes":
        # Predictions rise with the values, so counts of prediction bands say which band holds a rank: one pass for all cuts.
        bands = int(np.clip(np.ceil(1 / max(min(p.kappa, 1 / t), 1e-3)), 2 * t, 1024))
        band = np.minimum((f * bands).astype(np.int16), bands - 1)
        held = np.bincount(band, minlength=bands)
        upto = np.cumsum(held)
        out = []
        for rank in ranks.tolist():
            j = int(np.searchsorted(upto, rank, side="right"))
            place = rank - int(upto[j] - held[j])
            out.append(np.partition(x[band == j], place)[place])
        return np.maximum.accumulate(np.array(out))
    out = []
    for q, rank in zip(at, ranks.tolist(), strict=True):
        kappa = min(p.kappa, 1 / t)
        while True:
            low, high = f < q - kappa, f > q + kappa
            window = x[~low & ~high]
            below = int(low.sum())
            # Prediction rises with the value, so the window holds it if its rank falls inside; else it widens.
            inside = 0 <= rank - below < len(window)
            if kappa >= 1 or len(window) and (p.mode == "candidate_median" or inside):
                break
            kappa = max(2 * kappa, 0.01)
        if p.mode == "candidate_median":
            out.append(np.sort(window)[(len(window) - 1) // 2] if len(window) else np.median(x))
        else:
            place = min(max(rank - below, 0), len(window) - 1)
            out.append(np.partition(window, place)[place])
    return np.maximum.accumulate(np.array(out))


def dealt(side: np.ndarray, t: int) -> list[np.ndarray]:
    """The places of each side's members, in order: one stable pass over small numbers."""
    order = np.argsort(side.astype(np.int16), kind="stable")
    ends = np.cumsum(np.bincount(side, minlength=t)).tolist()
    return [order[a:b] for a, b in zip([0, *ends], ends, strict=False)]


def split(points: np.ndarray, pids: np.ndarray, idx: np.ndarray, depth: int, p: Params, draw: np.random.Generator, t: int | None = None) -> tuple[int, np.ndarray, list[np.ndarray]] | None:
    """(dimension, cuts, children's points), or None where no coordinate can be cut."""
    d = points.shape[1]
    t = t or (p.fan(len(idx)) if p.t == "per_node" else p.t)
    spread = np.ptp(points[idx], axis=0) if p.split == "widest" else points[idx].var(0) if p.split == "max_variance" else None
    dims = [(depth + i) % d for i in range(d)] if spread is None else np.argsort(-spread, kind="stable").tolist()
    for dim in dims:
        x = points[idx, dim]
        if x.min() == x.max() or t < 2:
            continue
        if p.mode == "sort":
            order = np.lexsort((pids[idx], x))
            cuts = [i * len(idx) // t for i in range(t + 1)]
            # Equal-count cuts by (value, pid); values that a cut divides are told apart by rank, so bounds do the routing.
            kids = [idx[order[a:b]] for a, b in zip(cuts, cuts[1:], strict=False)]
            return dim, x[order[[max(c - 1, 0) for c in cuts[1:-1]]]], kids
        if len(idx) <= p.small and p.mode in ("inverse", "rank_corrected"):
            order = np.argsort(x, kind="stable")  # few points: their order statistics and their sides from one sort
            ranked = x[order]
            pivots = ranked[np.maximum(-(-np.arange(1, t) * len(idx) // t) - 1, 0)]
            cuts = [0, *np.searchsorted(ranked, pivots, side="right").tolist(), len(idx)]
            if max(b - a for a, b in zip(cuts, cuts[1:], strict=False)) < len(idx):
                return dim, pivots, [idx[order[a:b]] for a, b in zip(cuts, cuts[1:], strict=False)]
            continue
        pivots = find_pivots(x, t, p, draw)
        side = np.searchsorted(pivots, x, side="left")
        if side.min() != side.max():
            return dim, pivots, [idx[part] for part in dealt(side, t)]
    return None


def build(points: np.ndarray, pids: np.ndarray, p: Params, idx: np.ndarray | None = None, depth: int = 0, t: int | None = None) -> Node:
    """A tree over points[idx]; the first cut may be given its number of children."""
    draw = np.random.default_rng([p.seed, depth, 0 if idx is None else len(idx)])
    idx = np.arange(len(points)) if idx is None else idx
    if p.t == "auto":
        p = Params(**{**p.__dict__, "t": p.fan(len(idx))})
    bare = lambda at, n: Node(at, n, None, None, None, 0.0)
    root = bare(depth, len(idx))
    open_nodes = [(root, idx, t)]
    while open_nodes:
        node, mine, fan = open_nodes.pop()
        cut = None if p.is_leaf(len(mine)) or node.depth > MAX_DEPTH else split(points, pids, mine, node.depth, p, draw, fan)
        if cut is None:
            node.idx = mine
            continue
        node.dim, node.pivots, parts = cut
        node.kids = [bare(node.depth + 1, len(part)) for part in parts]
        open_nodes.extend((kid, part, None) for kid, part in zip(node.kids, parts, strict=True))
    attach_volumes(root, points)
    return root


# --- search ------------------------------------------------------------------------------------------------


@dataclass
class Work:
    nodes_visited: int = 0
    leaves_visited: int = 0
    points_accessed: int = 0
    pruned_nodes: int = 0

    @property
    def cost(self) -> int:
        return self.nodes_visited + self.points_accessed


def lower_bounds(node: Node, q: np.ndarray, ball: bool) -> np.ndarray:
    lo, hi, centre, radius = node.stack()
    if ball:
        return np.maximum(distances(centre, q) - radius, 0)
    gap = np.maximum(np.maximum(lo - q, q - hi), 0)
    return distances(gap, np.zeros(len(q)))


class _Best:
    """The k best (distance, pid), worst first."""

    def __init__(self, k: int, limit: float):
        self.k, self.limit, self.heap = k, limit, []

    @property
    def reach(self) -> float:
        return min(self.limit, -self.heap[0][0]) if len(self.heap) == self.k else self.limit

    def offer(self, d: np.ndarray, pids: np.ndarray) -> None:
        for i in np.flatnonzero(d <= self.reach):
            item = (-d[i], -int(pids[i]))
            if len(self.heap) < self.k:
                heapq.heappush(self.heap, item)
            elif item > self.heap[0]:
                heapq.heapreplace(self.heap, item)


def knn(root: Node, points: np.ndarray, pids: np.ndarray, q: np.ndarray, k: int, strategy: str = "box_dfs", child_order: str = "nearest", limit: float = np.inf, budget: int | None = None, dfs_bound: str = "own") -> tuple[list[tuple[float, int]], Work]:
    """The k nearest by (distance, pid) within limit, and the work."""
    near, far, work = nearest(root, points, pids, q, k, strategy, child_order, limit, budget, dfs_bound)
    return sorted(zip(far.tolist(), near.tolist(), strict=True)), work


def nearest(root: Node, points: np.ndarray, pids: np.ndarray, q: np.ndarray, k: int, strategy: str = "box_dfs", child_order: str = "nearest", limit: float = np.inf, budget: int | None = None, dfs_bound: str = "own") -> tuple[np.ndarray, np.ndarray, Work]:
    """(pids, distances, work) of the k nearest by (distance, pid) within limit, in no order. A node is left out only when it lies strictly beyond the k-th.

    dfs_bound "single": depth first prunes by boxes whatever the volume.
    """
    deep = strategy.endswith("dfs")
    ball = strategy.startswith("ball") and not (deep and dfs_bound == "single")
    if k >= root.n == len(pids) and limit == np.inf and budget is None and root.n:  # every point is an answer, every node is met
        nodes = [x for x, _, _ in preorder(root) if x.n]
        return pids, distances(points, q), Work(len(nodes), sum(x.idx is not None for x in nodes), root.n, 0)
    if k >= root.n:  # nothing but the limit can rule a node out
        return radius_search(root, points, pids, q, limit * (1 + 1e-12), ("ball_" if ball else "box_") + strategy.split("_")[1], budget=budget)
    best, work = _Best(k, limit * (1 + 1e-12)), Work()
    line: deque = deque([(0.0, root)])
    while line and root.n:
        bound, node = line.pop() if deep else line.popleft()
        if bound > best.reach * (1 + 1e-12):
            work.pruned_nodes += 1
            continue
        work.nodes_visited += 1
        if node.idx is not None:
            work.leaves_visited += 1
            work.points_accessed += len(node.idx)
            if len(node.idx):
                best.offer(distances(points[node.idx], q), pids[node.idx])
        else:
            bounds = lower_bounds(node, q, ball)
            order = np.argsort(bounds, kind="stable") if child_order == "nearest" else np.arange(len(bounds))
            reach = best.reach * (1 + 1e-12)
            for j in (order[::-1] if deep else order).tolist():
                if node.kids[j].n == 0:
                    continue
                if bounds[j] > reach:
                    work.pruned_nodes += 1
                else:
                    line.append((float(bounds[j]), node.kids[j]))
        if budget is not None and work.cost > budget:
            break
    return np.array([-p for _, p in best.heap], dtype=np.int64), np.array([-d for d, _ in best.heap]), work


@dataclass
class Flat:
    """A packed tree as arrays, nodes in preorder: a node's children that hold points are a run of kids, a leaf's points a run of points."""

    n: np.ndarray
    lo: np.ndarray
    hi: np.ndarray
    center: np.ndarray
    radius: np.ndarray
    is_leaf: np.ndarray
    kids: np.ndarray
    kids_at: np.ndarray
    kids_n: np.ndarray
    empty: np.ndarray  # children that hold no points
    points: np.ndarray
    pids: np.ndarray
    held_at: np.ndarray
    held_n: np.ndarray

    @classmethod
    def of(cls, packed: bytes) -> Flat:
        z = np.load(io.BytesIO(packed), allow_pickle=False)
        a = {k: z[k] for k in ("parent", "n", "lo", "hi", "center", "radius", "is_leaf", "idx", "idx_n", "points", "pids")}
        parent, idx = a["parent"], a["idx"].astype(np.int64)
        full = np.flatnonzero((a["n"] > 0) & (parent >= 0))
        many, held = np.bincount(parent[full], minlength=len(parent)), a["idx_n"].astype(np.int64)
        kids = full[np.argsort(parent[full], kind="stable")]
        return cls(a["n"], a["lo"], a["hi"], a["center"], a["radius"], a["is_leaf"].astype(bool), kids, np.cumsum(many) - many, many, np.bincount(parent[(a["n"] == 0) & (parent >= 0)], minlength=len(parent)), a["points"][idx], a["pids"][idx], np.cumsum(held) - held, held)


LEAF_GROUP = 1024


class Lone:
    """A packed tree for walks that go alone: the volumes of a node's children, and a leaf's points, lie side by side."""

    def __init__(self, packed: bytes):
        self.flat = t = Flat.of(packed)
        self.lo, self.hi, self.center, self.radius = t.lo[t.kids], t.hi[t.kids], t.center[t.kids], t.radius[t.kids]
        self.columns = np.ascontiguousarray(t.points.T)
        self.kids, self.is_leaf = t.kids.tolist(), t.is_leaf.tolist()
        ends = lambda at, n: list(zip(at.tolist(), (at + n).tolist(), strict=True))
        self.group = self._groups(t)
        self.run = [h if leaf else k for leaf, h, k in zip(self.is_leaf, ends(t.held_at, t.held_n), ends(t.kids_at, t.kids_n), strict=True)]
        self.first, self.held, self.leaf = t.held_at[t.kids], t.n[t.kids], t.is_leaf[t.kids]  # the points below a node are a run as well
        self.full = int((t.n > 0).sum()), int((t.is_leaf & (t.n > 0)).sum()), int(t.n[0]), 0

    @staticmethod
    def _groups(t: Flat) -> list[tuple[int, int]]:
        """For each leaf the run of points, LEAF_GROUP at most, of the leaves beside it under one parent: their distances are computed together."""
        leaf, parent = t.is_leaf[t.kids], np.repeat(np.arange(len(t.kids_n)), t.kids_n)
        out = list(zip(t.held_at.tolist(), (t.held_at + t.held_n).tolist(), strict=True))
        ends = [0, *(np.flatnonzero((parent[1:] != parent[:-1]) | ~leaf[1:] | ~leaf[:-1]) + 1).tolist(), len(t.kids)]
        kids = t.kids.tolist()
        for a, b in zip(ends, ends[1:], strict=False):
            if b > a and leaf[a]:
                first, last = out[kids[a]][0], out[kids[b - 1]][1]
                if last - first <= LEAF_GROUP:
                    for i in kids[a:b]:
                        out[i] = first, last
        return out

    def nearest(self, q: np.ndarray, k: int, strategy: str = "box_dfs", child_order: str = "nearest", limit: float = np.inf, budget: int | None = None, dfs_bound: str = "own") -> tuple[np.ndarray, np.ndarray, Work]:
        """nearest() of the tree, with its answers and counters; a budget only for a k below its points."""
        deep = strategy.endswith("dfs")
        ball = strategy.startswith("ball") and not (deep and dfs_bound == "single")
        t = self.flat
        if k >= t.n[0] and limit == np.inf and t.n[0]:  # every point is an answer, every node is met
            return t.pids, distances(t.points, q), Work(*self.full)
        if k >= t.n[0]:
            return self.within(q, limit * (1 + 1e-12), ("ball_" if ball else "box_") + strategy.split("_")[1])
        columns, pids, is_leaf, run, kids, zeros = list(zip(self.columns, q.tolist(), strict=True)), self.flat.pids, self.is_leaf, self.run, self.kids, np.zeros(len(q))
        limit *= 1 + 1e-12
        start = end = -1  # the group of leaves whose distances are told
        near, far, met = [], [], 0  # what came within reach, the best of it being told by pid at the end
        best = np.empty(0)  # the k least distances so far
        reach, slack = limit, limit * (1 + 1e-12)
        work = Work()
        line: deque = deque([(0.0, 0)])
        take = line.pop if deep else line.popleft
        while line:
            bound, node = take()
            if bound > slack:
                work.pruned_nodes += 1
                continue
            work.nodes_visited += 1
            a, b = run[node]
            if is_leaf[node]:
                work.leaves_visited += 1
                work.points_accessed += b - a
                if not start <= a < b <= end:
                    start, end = self.group[node]
                    told = 0.0
                    for column, x in columns:
                        gap = column[start:end] - x
                        gap *= gap
                        told += gap
                    told = np.sqrt(told)
                d = told[a - start : b - start]
                hit = (d <= reach).nonzero()[0]
                if len(hit):
                    d = d[hit]
                    far.append(d)
                    near.append(pids[a:b][hit])
                    met += len(hit)
                    if met >= k:
                        best = np.concatenate((best, d) if len(best) else far)
                        best.partition(k - 1)
                        best = best[:k]
                        reach = min(limit, float(best[k - 1]))
                        slack = reach * (1 + 1e-12)
            else:
                if ball:
                    bounds = np.maximum(distances(self.center[a:b], q) - self.radius[a:b], 0)
                else:
                    bounds = distances(np.maximum(np.maximum(self.lo[a:b] - q, q - self.hi[a:b]), 0), zeros)
                order = np.argsort(bounds, kind="stable").tolist() if child_order == "nearest" else range(b - a)
                low = bounds.tolist()
                for j in reversed(order) if deep else order:
                    if low[j] > slack:
                        work.pruned_nodes += 1
                    else:
                        line.append((low[j], kids[a + j]))
            if budget is not None and work.cost > budget:
                break
        if not met:
            return np.empty(0, np.int64), np.empty(0), work
        near, far = np.concatenate(near), np.concatenate(far)
        if met > k:
            kept = np.lexsort((near, far))[:k]
            near, far = near[kept], far[kept]
        return near, far, work

    def within(self, q: np.ndarray, r: float, strategy: str = "box_dfs", accept_inside: bool = False) -> tuple[np.ndarray, np.ndarray, Work]:
        """radius_search() of the tree, with its answers and counters. No node depends on a distance: siblings are opened together, the points of all leaves met at the end."""
        ball, deep, work = strategy.startswith("ball"), strategy.endswith("dfs"), Work()
        t, empty, zeros = self.flat, self.flat.empty, np.zeros(len(q))
        if not t.n[0]:
            return np.empty(0, np.int64), np.empty(0), work
        slack, inside = r * (1 + 1e-12) + 1e-300, r * (1 - 1e-12)
        work.nodes_visited = 1
        if self.is_leaf[0] or accept_inside and float(distances(t.center[:1], q)[0]) + t.radius[0] <= inside:
            work.leaves_visited, work.points_accessed = 1, int(t.n[0])
            far = distances(t.points, q)
            hit = far <= r
            return t.pids[hit], far[hit], work
        met = []  # places among kids
        line: deque = deque([np.zeros(1, dtype=np.int64)])  # siblings, opened together
        take = line.pop if deep else line.popleft
        while line:
            group = take()
            parent, at, _ = _runs(t.kids_at[group], t.kids_n[group])
            if ball or accept_inside:
                apart = distances(self.center[at], q)
            if ball:
                low = apart - self.radius[at]
            else:
                low = distances(np.maximum(np.maximum(self.lo[at] - q, q - self.hi[at]), 0), zeros)
            near = (low <= slack).nonzero()[0]
            work.nodes_visited += len(near)
            work.pruned_nodes += len(at) - len(near) + int(empty[group].sum())
            place = at[near]
            whole = self.leaf[place]
            if accept_inside:
                whole = whole | (apart[near] + self.radius[place] <= inside)
            if whole.any():
                met.append(place[whole])
                near, place = near[~whole], place[~whole]
            if len(place):
                parent = parent[near]
                line.extend(np.split(t.kids[place], np.flatnonzero(parent[1:] != parent[:-1]) + 1))
        if not met:
            return np.empty(0, np.int64), np.empty(0), work
        met = np.concatenate(met)
        work.leaves_visited, work.points_accessed = len(met), int(self.held[met].sum())
        start, end = self.first[met], self.first[met] + self.held[met]
        order = np.argsort(start)  # leaves beside one another are one run of points
        start, end = start[order], end[order]
        new = np.flatnonzero(start[1:] != end[:-1])
        runs = [slice(a, b) for a, b in zip(start[np.append(0, new + 1)].tolist(), end[np.append(new, len(end) - 1)].tolist(), strict=True)]
        far = np.zeros(work.points_accessed)
        for column, x in zip(self.columns, q.tolist(), strict=True):
            gap = np.concatenate([column[run] for run in runs])
            gap -= x
            gap *= gap
            far += gap
        np.sqrt(far, out=far)
        hit = far <= r
        return np.concatenate([t.pids[run] for run in runs])[hit], far[hit], work


STEP_NUMBERS = 1_000_000  #: points that a step of many walks looks at together


def _runs(start: np.ndarray, count: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(owner, place, ordinal) of the members of runs, one run after the other."""
    owner = np.repeat(np.arange(len(count)), count)
    ordinal = np.arange(len(owner)) - np.repeat(np.cumsum(count) - count, count)
    return owner, np.repeat(start, count) + ordinal, ordinal


def _far(points: np.ndarray, at: np.ndarray, q: np.ndarray, owner: np.ndarray) -> np.ndarray:
    total = np.zeros(len(at))
    for i in range(points.shape[1]):
        gap = points[at, i] - q[owner, i]
        total += gap * gap
    return np.sqrt(total)


def _offer_all(t: Flat, leaf: np.ndarray, rows: np.ndarray, q: np.ndarray, k: np.ndarray, reach: np.ndarray, near: np.ndarray, far: np.ndarray) -> None:
    """Each row meets the points of its leaf: near and far keep its best by (distance, pid), best first."""
    most = far.shape[1]
    ends = np.flatnonzero(np.diff(np.cumsum(t.held_n[leaf]) // STEP_NUMBERS)) + 1
    for mine in np.split(np.arange(len(rows)), ends) if len(ends) else [np.arange(len(rows))]:
        owner, at, _ = _runs(t.held_at[leaf[mine]], t.held_n[leaf[mine]])
        d = _far(t.points, at, q[rows[mine]], owner)
        hit = np.flatnonzero(d <= reach[rows[mine]][owner])
        if not len(hit):
            continue
        owner, d, ids = owner[hit], d[hit], t.pids[at[hit]]
        count = np.bincount(owner, minlength=len(mine))
        if count.max() > 4 * most + 64:  # a leaf of equal points: only the best of it go on
            order = np.lexsort((ids, d, owner))
            owner, d, ids = owner[order], d[order], ids[order]
            keep = _runs(np.cumsum(count) - count, count)[2] < most
            owner, d, ids = owner[keep], d[keep], ids[keep]
            count = np.minimum(count, most)
        got = np.flatnonzero(count)
        back = np.zeros(len(mine), dtype=np.int64)
        back[got] = np.arange(len(got))
        place = most + _runs(np.cumsum(count) - count, count)[2]
        width = most + int(count.max())
        ds, ps = np.full((len(got), width), np.inf), np.full((len(got), width), np.iinfo(np.int64).max)
        at_rows = rows[mine[got]]
        ds[:, :most], ps[:, :most] = far[at_rows], near[at_rows]
        ds[back[owner], place], ps[back[owner], place] = d, ids
        best = np.lexsort((ps, ds), axis=1)[:, :most]
        far[at_rows], near[at_rows] = np.take_along_axis(ds, best, 1), np.take_along_axis(ps, best, 1)
        reach[at_rows] = np.minimum(reach[at_rows], far[at_rows, k[at_rows] - 1])


def nearest_together(t: Flat, q: np.ndarray, k: np.ndarray, limit: np.ndarray, strategy: str, child_order: str = "nearest", budget: np.ndarray | None = None, dfs_bound: str = "own") -> tuple[list[tuple[np.ndarray, np.ndarray]], np.ndarray]:
    """nearest() for many queries, one node of each at a step: ((pids, distances) of each, and its nodes visited, leaves, points, pruned).

    Every walk meets its nodes in its own order, so answers and counters are those of nearest(). Each k is less
    than the points of the tree.
    """
    deep = strategy.endswith("dfs")
    ball = strategy.startswith("ball") and not (deep and dfs_bound == "single")
    m, most = len(q), int(k.max())
    near, far = np.full((m, most), np.iinfo(np.int64).max), np.full((m, most), np.inf)
    reach, work = limit * (1 + 1e-12), np.zeros((m, 4), dtype=np.int64)
    line, bounds = np.zeros((m, 64), dtype=np.int32), np.zeros((m, 64))
    head, tail = np.zeros(m, dtype=np.int64), np.ones(m, dtype=np.int64)
    while len(rows := np.flatnonzero(head < tail)):
        if deep:
            tail[rows] -= 1
            at = tail[rows]
        else:
            at = head[rows]
            head[rows] += 1
        node, beyond = line[rows, at], bounds[rows, at] > reach[rows] * (1 + 1e-12)
        work[rows[beyond], 3] += 1
        rows, node = rows[~beyond], node[~beyond]
        work[rows, 0] += 1
        leaf = t.is_leaf[node]
        if leaf.any():
            mine, met = rows[leaf], node[leaf]
            work[mine, 1] += 1
            work[mine, 2] += t.held_n[met]
            _offer_all(t, met, mine, q, k, reach, near, far)
        if not leaf.all():
            mine, met = rows[~leaf], node[~leaf]
            owner, at, _ = _runs(t.kids_at[met], t.kids_n[met])
            kid, x = t.kids[at], q[mine]
            if ball:
                low = np.maximum(_far(t.center, kid, x, owner) - t.radius[kid], 0)
            else:
                low = np.zeros(len(kid))
                for i in range(q.shape[1]):
                    gap = np.maximum(np.maximum(t.lo[kid, i] - x[owner, i], x[owner, i] - t.hi[kid, i]), 0)
                    low += gap * gap
                low = np.sqrt(low)
            open_ = low <= (reach[mine] * (1 + 1e-12))[owner]
            work[mine, 3] += np.bincount(owner[~open_], minlength=len(mine))
            owner, kid, low = owner[open_], kid[open_], low[open_]
            if child_order == "nearest":
                order = np.lexsort((low, owner))
                kid, low = kid[order], low[order]
            count = np.bincount(owner, minlength=len(mine))
            place = _runs(np.zeros(len(mine), dtype=np.int64), count)[2]
            if deep:
                place = count[owner] - 1 - place
            if (need := int((tail[mine] + count).max())) > line.shape[1]:
                more = max(need, 2 * line.shape[1]) - line.shape[1]
                line, bounds = np.pad(line, ((0, 0), (0, more))), np.pad(bounds, ((0, 0), (0, more)))
            line[mine[owner], tail[mine][owner] + place], bounds[mine[owner], tail[mine][owner] + place] = kid, low
            tail[mine] += count
        if budget is not None:
            spent = rows[work[rows, 0] + work[rows, 2] > budget[rows]]
            tail[spent] = head[spent]
    found = np.isfinite(far) & (np.arange(most) < k[:, None])
    return [(near[i, f], far[i, f]) for i, f in enumerate(found)], work


def radius_search(root: Node, points: np.ndarray, pids: np.ndarray, q: np.ndarray, r: float, strategy: str = "box_dfs", accept_inside: bool = False, budget: int | None = None) -> tuple[np.ndarray, np.ndarray, Work]:
    """(pids, distances, work) of all points within r, the rim included."""
    ball, deep, work = strategy.startswith("ball"), strategy.endswith("dfs"), Work()
    found, far = [], []
    line: deque = deque([root])
    slack = r * (1 + 1e-12) + 1e-300
    while line and root.n:
        node = line.pop() if deep else line.popleft()
        work.nodes_visited += 1
        if node.idx is not None or accept_inside and float(distances(node.center[None, :], q)[0]) + node.radius <= r * (1 - 1e-12):
            mine = node.idx if node.idx is not None else np.concatenate([leaf.idx for leaf in leaves(node)])
            work.leaves_visited += 1
            work.points_accessed += len(mine)
            if len(mine):
                d = distances(points[mine], q)
                hit = d <= r
                found.append(pids[mine[hit]])
                far.append(d[hit])
        else:
            for j, bound in enumerate(lower_bounds(node, q, ball)):
                if bound > slack or node.kids[j].n == 0:
                    work.pruned_nodes += 1
                else:
                    line.append(node.kids[j])
        if budget is not None and work.cost > budget:
            break
    return (np.concatenate(found) if found else np.empty(0, np.int64)), (np.concatenate(far) if far else np.empty(0)), work


def leaves(root: Node) -> list[Node]:
    out, line = [], [root]
    while line:
        node = line.pop()
        if node.idx is not None:
            out.append(node)
        else:
            line.extend(reversed(node.kids))
    return out


def nearest_leaf(root: Node, q: np.ndarray) -> list[int]:
    """The path of ordinals to the leaf that a point belongs to: nearest child by box, the first of equals."""
    path, node = [], root
    while node.idx is None:
        bounds = lower_bounds(node, q, False)
        bounds[[k.n == 0 for k in node.kids]] = np.inf
        j = int(bounds.argmin())
        path.append(j)
        node = node.kids[j]
    return path


# --- insertion ---------------------------------------------------------------------------------------------


def allowed_omega(omega: float, t: int) -> float:
    """Equal children meet the criterion only above (t - 1) / t: the threshold is raised to there where needed."""
    least = (t - 1) / t
    return omega if omega > least else least + (1 - least) / 2


def range_balanced(sizes: list[int], i0: int, i1: int, omega: float, span: str = "count") -> bool:
    """The criterion for siblings i0..i1 as one; span "count" multiplies by their number, "printed" by i1 - i0."""
    many = i1 - i0 + 1 if span == "count" else i1 - i0
    return sum(sizes[i0 : i1 + 1]) < many * omega * sum(sizes) / (len(sizes) - 1)


def rebuild_range(sizes: list[int], omega: float, span: str = "count") -> tuple[int, int] | None:
    """The contiguous siblings of fewest points that hold the largest violator and are balanced together; None if all are."""
    if len(sizes) < 2 or not sum(sizes):
        return None
    bad = [i for i in range(len(sizes)) if not range_balanced(sizes, i, i, omega)]
    if not bad:
        return None
    worst = max(bad, key=lambda i: (sizes[i], -i))
    options = [(sum(sizes[a : b + 1]), b - a, a, b) for a in range(worst + 1) for b in range(worst, len(sizes)) if range_balanced(sizes, a, b, omega, span)]
    if not options:
        return 0, len(sizes) - 1
    return min(options)[2:]


def insert(root: Node, points: np.ndarray, pids: np.ndarray, fresh: np.ndarray, p: Params, rebuild: str = "selective") -> list[dict]:
    """Push the positions `fresh` down in groups, split leaves over capacity, then rebalance from the top.

    Returns a log row for each rebuild. rebuild: "selective" (fewest siblings), "full" (all children), "none".
    """
    if p.t == "auto":
        p = Params(**{**p.__dict__, "t": max(2, len(root.kids) or p.fan(root.n + len(fresh)))})
    touched: list[Node] = []
    log: list[dict] = []
    line = [(root, fresh)]
    while line:
        node, mine = line.pop()
        old = node.n
        grow(node, points[mine])
        if node.idx is not None:
            node.idx = np.concatenate((node.idx, mine))
            if not p.is_leaf(len(node.idx)):
                new = build(points, pids, p, node.idx, node.depth)
                for a in ("n", "lo", "hi", "center", "radius", "dim", "pivots", "kids", "idx", "bounds"):
                    setattr(node, a, getattr(new, a))
            continue
        node.bounds = None
        touched.append(node)
        side = np.searchsorted(node.pivots, points[mine, node.dim], side="left")
        assert node.n == old + len(mine)
        if p.check == "before" and rebuild != "none" and len(node.kids) > 1:
            # The children's sizes as they would be: what is out of balance is built at once, the batch's share with it.
            sizes = (np.array([k.n for k in node.kids]) + np.bincount(side, minlength=len(node.kids))).tolist()
            found = rebuild_range(sizes, allowed_omega(p.omega, len(sizes)))
            if found is not None:
                i0, i1 = (0, len(sizes) - 1) if rebuild == "full" else found
                came = mine[(side >= i0) & (side <= i1)]
                log.append(_rebuild(node, points, pids, p, i0, i1, came, mine))
                if log[-1]["reason"] == "tie":
                    continue
                mine, side = mine[(side < i0) | (side > i1)], side[(side < i0) | (side > i1)]
        line.extend((node.kids[j], mine[side == j]) for j in np.unique(side).tolist())
    done: set[int] = set()
    for node in sorted(touched, key=lambda x: x.depth):  # the highest violation first; what is rebuilt holds no other
        if id(node) in done or rebuild == "none" or len(node.kids) < 2:
            continue
        sizes = [k.n for k in node.kids]
        found = rebuild_range(sizes, allowed_omega(p.omega, len(sizes)))
        if found is None:
            continue
        i0, i1 = (0, len(sizes) - 1) if rebuild == "full" else found
        line2 = list(node.kids[i0 : i1 + 1])
        while line2:
            k = line2.pop()
            done.add(id(k))
            line2.extend(k.kids)
        log.append(_rebuild(node, points, pids, p, i0, i1))
    return log


def _rebuild(node: Node, points: np.ndarray, pids: np.ndarray, p: Params, i0: int, i1: int, came: np.ndarray | None = None, all_came: np.ndarray | None = None) -> dict:
    """Cut children i0..i1 anew with the points that came to them; the whole node where its coordinate cannot be cut there."""
    none = np.empty(0, np.int64)
    mine = np.concatenate([leaf.idx for k in node.kids[i0 : i1 + 1] for leaf in leaves(k)] + [none if came is None else came])
    same = False
    if i1 > i0:
        again = split(points, pids, mine, node.depth, Params(**{**p.__dict__, "split": "cycle"}), np.random.default_rng([p.seed, len(mine)]), i1 - i0 + 1)
        same = again is not None and again[0] == node.dim
    if same:
        _, cuts, parts = again
        node.kids[i0 : i1 + 1] = [build(points, pids, p, part, node.depth + 1) for part in parts]
        node.pivots = np.concatenate((node.pivots[:i0], cuts, node.pivots[i1:]))
    else:
        mine = np.concatenate([leaf.idx for leaf in leaves(node)] + [none if all_came is None else all_came])
        new = build(points, pids, p, mine, node.depth)
        for a in ("dim", "pivots", "kids", "idx"):
            setattr(node, a, getattr(new, a))
    node.bounds = None
    return {"depth": node.depth, "i0": i0, "i1": i1, "points_rebuilt": len(mine), "points_full": node.n, "reason": "balance" if same else "tie"}


def grow(node: Node, more: np.ndarray) -> None:
    """Count and volumes after points came: the box exactly, the ball around the old centre."""
    if not len(more):
        return
    if node.n == 0:
        new = volume(more, node.depth)
        node.n, node.lo, node.hi, node.center, node.radius = new.n, new.lo, new.hi, new.center, new.radius
        return
    node.n += len(more)
    node.lo, node.hi = np.minimum(node.lo, more.min(0)), np.maximum(node.hi, more.max(0))
    node.radius = max(node.radius, float(distances(more, node.center).max()))


# --- routing by the upper tier ------------------------------------------------------------------------------


@dataclass
class Router:
    """A tree as arrays: a value moves from node to child level by level, all values together."""

    dim: np.ndarray
    cuts: np.ndarray  # (nodes, widest fan-out - 1), filled up with infinity
    first: np.ndarray  # a node's first child; a leaf is its own
    leaf: np.ndarray  # a leaf's number
    height: int

    @classmethod
    def of(cls, root: Node) -> Router:
        level, nodes, height = [root], [root], 0
        first: list[int] = []
        while level:
            kids = [k for x in level for k in x.kids]
            at = len(nodes)
            for x in level:
                first.append(at if x.kids else len(first))
                at += len(x.kids)
            nodes += kids
            level, height = kids, height + 1
        number = {id(x): i for i, x in enumerate(leaves(root))}
        cuts = np.full((len(nodes), max([len(x.kids) - 1 for x in nodes if x.kids], default=0)), np.inf)
        for i, x in enumerate(nodes):
            if x.kids:
                cuts[i, : len(x.kids) - 1] = x.pivots[: len(x.kids) - 1]
        return cls(np.array([max(x.dim, 0) for x in nodes]), cuts, np.array(first), np.array([number.get(id(x), -1) for x in nodes]), height - 1)

    def cells(self, points: np.ndarray) -> np.ndarray:
        at, row = np.zeros(len(points), dtype=np.int64), np.arange(len(points))
        for _ in range(self.height):
            x = points[row, self.dim[at]]
            at = self.first[at] + (self.cuts[at] < x[:, None]).sum(axis=1)
        return self.leaf[at]


# --- measures and packing ----------------------------------------------------------------------------------


def aepl(root: Node, convention: str = "sequential") -> tuple[float, int]:
    """(sum of comparisons over points, points)."""
    total, line = 0.0, [(root, 0.0)]
    while line:
        node, cost = line.pop()
        if node.idx is not None:
            total += cost * len(node.idx)
        else:
            t = len(node.kids)
            line.extend((k, cost + (min(j + 1, t - 1) if convention == "sequential" else np.log2(t))) for j, k in enumerate(node.kids))
    return total, root.n


def preorder(root: Node) -> list[tuple[Node, int, int]]:
    """(node, parent's place or -1, ordinal)."""
    out, line = [], [(root, -1, 0)]
    while line:
        node, parent, ordinal = line.pop()
        out.append((node, parent, ordinal))
        me = len(out) - 1
        line.extend((k, me, j) for j, k in reversed(list(enumerate(node.kids))))
    return out


def pack(root: Node, points: np.ndarray, pids: np.ndarray) -> bytes:
    nodes = preorder(root)
    leaf = [x.idx if x.idx is not None else np.empty(0, np.int64) for x, _, _ in nodes]
    cuts = [x.pivots if x.pivots is not None else np.empty(0) for x, _, _ in nodes]
    out = io.BytesIO()
    np.savez(
        out, points=points, pids=pids, parent=[p for _, p, _ in nodes], dim=[x.dim for x, _, _ in nodes], depth=[x.depth for x, _, _ in nodes], n=[x.n for x, _, _ in nodes],
        lo=np.array([x.lo for x, _, _ in nodes]), hi=np.array([x.hi for x, _, _ in nodes]), center=np.array([x.center for x, _, _ in nodes]), radius=[x.radius for x, _, _ in nodes],
        is_leaf=[x.idx is not None for x, _, _ in nodes], idx=np.concatenate(leaf), idx_n=[len(x) for x in leaf], cuts=np.concatenate(cuts), cuts_n=[len(x) for x in cuts],
    )
    return out.getvalue()


def unpack(packed: bytes) -> tuple[Node, np.ndarray, np.ndarray]:
    z = np.load(io.BytesIO(packed), allow_pickle=False)
    a = {k: z[k] for k in z.files}
    idx, cuts = np.split(a["idx"], np.cumsum(a["idx_n"])[:-1]), np.split(a["cuts"], np.cumsum(a["cuts_n"])[:-1])
    nodes: list[Node] = []
    for i, parent in enumerate(a["parent"].tolist()):
        node = Node(int(a["depth"][i]), int(a["n"][i]), a["lo"][i], a["hi"][i], a["center"][i], float(a["radius"][i]), int(a["dim"][i]))
        if a["is_leaf"][i]:
            node.idx = idx[i].astype(np.int64)
        else:
            node.pivots = cuts[i]
        nodes.append(node)
        if parent >= 0:
            nodes[parent].kids.append(node)
    return nodes[0], a["points"], a["pids"]
