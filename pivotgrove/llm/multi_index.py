"""Operator 5: embedding near-duplicates through an inverted multi-index.

Vectors are scaled to length one and cut in two halves, each with a codebook of its own; the pairs of codes
are the cells of a product grid. A vector visits the nearest cells, found in order by the traversal that
walks both sorted code lists together, until the share of simulated neighbours at the threshold itself that
lie in the visited cells reaches the target; it is compared there in double precision.

Equal vectors are one class with a weight. Only counts and joining links leave a cell: a pair counts once
for each side, also when both visit the other's cell, because each vector carries the list of its visits. A
crowded cell is cut into blocks, and each pair of blocks is a task of bounded size.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pivotgrove.llm.tables import read
from pivotgrove.runtime import components, discard, materialise, ship

THRESHOLD, TARGET = 0.95, 0.995
SAMPLE = 20_000  #: vectors that the codebooks and the number of visits are fitted on at most
CELL_ROWS = 256  #: vectors a cell should hold
CODES_LEAST, CODES_MOST = 4, 2048  #: up to a billion vectors the cells stay as full; then they grow
BLOCK = 1024
SEED = 11


def codebook(x: np.ndarray, codes: int, rounds: int = 8, seed: int = SEED) -> np.ndarray:
    """Lloyd's rounds from drawn rows; a code that loses all rows keeps its place."""
    draw = np.random.default_rng(seed)
    centres = x[draw.choice(len(x), min(codes, len(x)), replace=False)].copy()
    for _ in range(rounds):
        near = ((centres**2).sum(1) - 2 * x @ centres.T).argmin(1)
        for c in range(len(centres)):
            if (mine := near == c).any():
                centres[c] = x[mine].mean(0)
    return centres


def traverse(first: np.ndarray, second: np.ndarray, visits: int) -> list[int]:
    """The cells (code of the first half * codes of the second + code of the second) by ascending distance sum."""
    a, b = np.argsort(first, kind="stable"), np.argsort(second, kind="stable")
    da, db = first[a].tolist(), second[b].tolist()
    width, out, heap, met = len(db), [], [(da[0] + db[0], 0, 0)], {(0, 0)}
    while heap and len(out) < visits:
        _, i, j = heapq.heappop(heap)
        out.append(int(a[i]) * width + int(b[j]))
        for i2, j2 in ((i + 1, j), (i, j + 1)):
            if i2 < len(da) and j2 < width and (i2, j2) not in met:
                met.add((i2, j2))
                heapq.heappush(heap, (da[i2] + db[j2], i2, j2))
    return out


class MultiIndex:
    def __init__(self, books: tuple[np.ndarray, np.ndarray], visits: int):
        self.books, self.visits = books, visits

    def distances(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        half = self.books[0].shape[1]
        return tuple((c**2).sum(1) - 2 * part @ c.T for part, c in zip((x[:, :half], x[:, half:]), self.books, strict=True))

    def route(self, x: np.ndarray) -> list[list[int]]:
        """The visits of each row; the first is its own cell."""
        return [traverse(p, q, self.visits) for p, q in zip(*self.distances(x), strict=True)]

    def ranks(self, x: np.ndarray, cells: np.ndarray) -> np.ndarray:
        """How many cells lie as near to each row as its given cell, itself left out: counted by code, not walked."""
        out = np.empty(len(x), dtype=np.int64)
        width = len(self.books[1])
        for r, (p, q, c) in enumerate(zip(*self.distances(x), cells.tolist(), strict=True)):
            # The sums below stay on one side of the cell's own sum, whatever the rounding.
            limit = p[c // width] + q[c % width]
            out[r] = np.searchsorted(np.sort(q), limit - p + 1e-12, side="right").sum() - 1
        return np.maximum(out, 0)

    def homes(self, x: np.ndarray) -> np.ndarray:
        p, q = self.distances(x)
        return p.argmin(1) * len(self.books[1]) + q.argmin(1)

    @classmethod
    def fit(cls, sample: np.ndarray, rows: int, threshold: float = THRESHOLD, target: float = TARGET, seed: int = SEED) -> MultiIndex:
        codes = int(min(CODES_MOST, max(CODES_LEAST, np.ceil(np.sqrt(rows / CELL_ROWS)))))
        half = max(1, sample.shape[1] // 2)
        books = codebook(sample[:, :half], codes, seed=seed), codebook(sample[:, half:], codes, seed=seed + 1)
        index = cls(books, len(books[0]) * len(books[1]))
        draw = np.random.default_rng(seed)
        x = sample[draw.choice(len(sample), min(2000, len(sample)), replace=False)]
        side = draw.normal(size=x.shape)
        side -= (side * x).sum(1, keepdims=True) * x
        side /= np.maximum(np.linalg.norm(side, axis=1, keepdims=True), 1e-300)
        y = threshold * x + np.sqrt(1 - threshold**2) * side
        # A pair is found when either side visits the other's cell.
        rank = np.minimum(index.ranks(x, index.homes(y)), index.ranks(y, index.homes(x)))
        index.visits = int(np.quantile(rank, target, method="higher")) + 1
        return index


def _unit(lists: pa.Array) -> np.ndarray:
    width = len(lists[0])
    x = np.asarray(lists.flatten(), dtype=np.float64).reshape(len(lists), width)
    return x / np.linalg.norm(x, axis=1, keepdims=True)


def _route_kernel(shared):
    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        index = MultiIndex(*shared.value)
        for batch in batches:
            for at in range(0, batch.num_rows, 2048):
                rows = batch.slice(at, 2048)
                visits = index.route(_unit(rows.column(2)))
                # The vector travels as it was given: 4 bytes a component where it came as floats.
                raw = np.asarray(rows.column(2).flatten()).reshape(len(visits), -1)
                yield pa.RecordBatch.from_arrays([rows.column(0), rows.column(1), pa.array([v.tobytes() for v in raw], pa.binary()), pa.array(visits, pa.list_(pa.int32()))], ["rep", "weight", "raw", "visits"])

    return kernel


def _cell_kernel(threshold: float, component: type):
    def kernel(table: pa.Table) -> pa.Table:
        rep, weight = table["rep"].to_numpy(), table["weight"].to_numpy()
        raw = np.vstack([np.frombuffer(v.as_py(), component) for v in table["raw"]]).astype(np.float64)
        unit = raw / np.linalg.norm(raw, axis=1, keepdims=True)
        entry, probe = np.flatnonzero(table["entry"].to_numpy()), np.flatnonzero(~table["entry"].to_numpy())
        gain = np.zeros(len(rep), dtype=np.int64)
        links: list[tuple[int, int]] = []
        if len(entry) and len(probe):
            home = table["home"].to_numpy()  # a row's own cell
            slots, inverse = np.unique(home[probe], return_inverse=True)
            seen = np.zeros((len(entry), len(slots)), dtype=bool)  # does the entry visit the probe's cell?
            lists = table["visits"].take(pa.array(entry)).combine_chunks()
            flat = np.asarray(lists.flatten())
            at = np.minimum(np.searchsorted(slots, flat), len(slots) - 1)
            hit = slots[at] == flat
            owner = np.repeat(np.arange(len(entry)), np.asarray(lists.value_lengths()))
            seen[owner[hit], at[hit]] = True
            near = (unit[probe] @ unit[entry].T >= threshold) & (rep[probe][:, None] != rep[entry][None, :])
            gain[probe] += near @ weight[entry]
            p, e = np.nonzero(near)
            alone = ~seen[e, inverse[p]]  # the entry never comes to the probe's cell: the pair counts for it here
            np.add.at(gain, entry[e[alone]], weight[probe[p[alone]]])
            parent = list(range(len(rep)))

            def root(i: int) -> int:
                while parent[i] != i:
                    parent[i] = i = parent[parent[i]]
                return i

            same = {}
            for i in range(len(rep)):  # a vector may stand here as entry and as probe
                parent[i] = same.setdefault(rep[i], i)
            for a, b in zip(probe[p].tolist(), entry[e].tolist(), strict=True):
                a, b = root(a), root(b)
                if a != b:
                    parent[max(a, b)] = min(a, b)
                    links.append((int(rep[a]), int(rep[b])))
        kept = np.flatnonzero(gain)
        n = len(kept) + len(links)
        return pa.table({"rep": pa.array([*rep[kept].tolist(), *[a for a, _ in links]], pa.int64()), "gain": pa.array([*gain[kept].tolist(), *[0] * len(links)], pa.int64()), "other": pa.array([*[None] * len(kept), *[b for _, b in links]], pa.int64())}) if n else pa.table({c: pa.array([], pa.int64()) for c in ("rep", "gain", "other")})

    return kernel


def near_duplicates(vectors: DataFrame, vec_id: str = "vec_id", embedding: str = "embedding", threshold: float = THRESHOLD, target: float = TARGET) -> DataFrame:
    """Per vector: vec_id, n_links, component_id, kept.

    Null, zero, empty and non-finite vectors, and those of another length than most, link with nothing. Rows
    that are repeated whole count once; of an id with several vectors the least is taken. An empty table gives
    no rows, other columns (label) are ignored. No pair under the threshold is linked; pairs at or over it are
    found with the target's probability at least, equal vectors always.
    """
    spark = vectors.sparkSession
    ship(spark)
    narrow = vectors.schema[embedding].dataType.simpleString() == "array<float>"
    kind = "array<float>" if narrow else "array<double>"
    rows = vectors.select(F.col(vec_id).cast("long").alias("vec_id"), F.col(embedding).cast(kind).alias("v")).groupBy("vec_id").agg(F.min("v").alias("v"))
    finite = F.forall("v", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists("v", lambda x: x != 0)
    good = materialise(rows.where(F.col("v").isNotNull() & finite), "vectors")
    width = good.groupBy(F.size("v").alias("d")).agg(F.count("*").alias("n")).orderBy(F.desc("n"), "d").first()
    ids = rows.select("vec_id")
    if width is None:
        return ids.select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"), F.lit(True).alias("kept"))
    good = good.where(F.size("v") == width.d)
    classes = materialise(good.groupBy("v").agg(F.min("vec_id").alias("rep"), F.count("*").alias("weight")).select("rep", "weight", "v"), "vector-classes")
    sample = classes.select(F.xxhash64("rep").alias("h"), "v").orderBy("h").limit(SAMPLE).toArrow()["v"].combine_chunks()
    index = MultiIndex.fit(_unit(sample), classes.count(), threshold, target)
    shared = spark.sparkContext.broadcast((index.books, index.visits))
    routed_at = materialise(classes.mapInArrow(_route_kernel(shared), "rep long, weight long, raw binary, visits array<int>"), "vectors-routed")
    routed = routed_at.withColumn("home", F.element_at("visits", 1))
    visits = routed.withColumn("cell", F.explode("visits"))
    blocks = lambda n: F.ceil(F.col(n) / BLOCK).cast("int")
    size = visits.groupBy("cell").agg(F.count("*").alias("probes"), F.sum((F.col("home") == F.col("cell")).cast("int")).alias("entries")).where("entries > 0")
    size = size.select("cell", blocks("probes").alias("pb"), blocks("entries").alias("eb"))  # a row for each cell that holds vectors
    part = lambda n: F.pmod(F.xxhash64("rep"), F.col(n)).cast("int")
    every = lambda n: F.explode(F.sequence(F.lit(0), F.col(n) - 1))
    common = ["cell", "p", "e", "rep", "weight", "raw", "home", "visits"]
    entries = routed.withColumn("cell", F.col("home")).join(size, "cell").withColumn("e", part("eb")).withColumn("p", every("pb")).select(*common, F.lit(True).alias("entry"))
    probes = visits.join(size, "cell").withColumn("p", part("pb")).withColumn("e", every("eb")).withColumn("visits", F.array().cast("array<int>")).select(*common, F.lit(False).alias("entry"))
    found = materialise(entries.union(probes).groupBy("cell", "p", "e").applyInArrow(_cell_kernel(threshold, np.float32 if narrow else np.float64), "rep long, gain long, other long"), "vectors-found")
    discard(routed_at)
    gains = found.where("other is null").groupBy("rep").agg(F.sum("gain").alias("gain"))
    linked = components(found.where("other is not null").select(F.col("rep").alias("src"), F.col("other").alias("dst")))
    named = classes.join(gains, "rep", "left").join(linked.withColumnRenamed("node", "rep"), "rep", "left").select("v", (F.coalesce("gain", F.lit(0)) + F.col("weight") - 1).alias("n_links"), F.coalesce("root", "rep").alias("component_id"))
    out = ids.join(good.join(named, "v").select("vec_id", "n_links", "component_id"), "vec_id", "left")
    name = F.coalesce("component_id", "vec_id")
    return out.select("vec_id", F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), name.alias("component_id"), (name == F.col("vec_id")).alias("kept"))


def op5_inverted_multi_index(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(read(spark, sf_dir, "embeddings"))
