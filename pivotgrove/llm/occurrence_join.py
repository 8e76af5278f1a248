"""Operator 7: exact n-gram Jaccard join by T-occurrence search with divided and skipped lists.

Two documents link when their shingle sets overlap enough, so a partner of x shares at least T shingles with
it. Under one order of all shingles, T - 1 - e of x's inverted lists need not be merged: of the others a
partner must stand in 1 + e at least. Spark merges these lists for the whole corpus (one exchange by shingle)
and drops every document with fewer than 1 + e shingles that any other document has; a passage that many
documents share is far from enough. What is left falls into small clusters. Inside a cluster the search is
done with the real list lengths: the short lists are merged through a heap that skips what cannot reach its
part of the threshold, and what reaches it is looked up in the long lists by binary search. Documents with
equal sets are one class.

Pairs that a link already joins are not looked up again, so a group of copies costs its members and not their
pairs, and what is written is at most a link per member and task. A cluster over the size of a task is cut
into blocks by set size, and each pair of blocks whose sizes permit a link is a task.
"""

from __future__ import annotations

import hashlib
import heapq
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from pivotgrove.llm.shingles import shingle_hashes
from pivotgrove.llm.tables import read, texts
from pivotgrove.runtime import components, discard, giving_back, materialise, ship

WORDS, PERCENT = 4, 85
TASK_SHINGLES = 1_000_000
BROADCAST_ROWS = 100_000
PRUNING_ROUNDS = 2
LONG_SHARE = 0.01  #: the larger, the fewer lists count as long
HEAP_MOST = 512  #: postings that go through the heap; more are counted in one array
PROBE_COST = 16_384  #: postings that are merged in the time of a candidate's probes
HOT_IN, HOT_HELD, HOT_MOST = 64, 16, 1000  #: a shingle is dealt as hot if so many of one in HOT_IN keys have it


def least_overlap(size: int, percent: int) -> int:
    """Shingles that a set of this size shares at least with any partner: percent of the larger of the two."""
    return -(-percent * size // 100)


def _digest(hashes: np.ndarray) -> bytes:
    return hashlib.blake2b(hashes.tobytes(), digest_size=16).digest()


def slack(size: int, percent: int) -> int:
    """e: how many more lists than need be are merged, half as many again."""
    due = least_overlap(size, percent)
    return max(0, min((size - due + 1) // 2, due - 1))


def required(size: int, percent: int) -> int:
    """Shingles of a document's merged lists that any partner, also the smallest one, shares with it at least."""
    return 1 + min(slack(size, percent), slack(least_overlap(size, percent), percent))


def _prefix_kernel(words: int, percent: int):
    """Each document's size, digest and merged shingles: the least ones by hash, and how many must be shared."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sizes, digests, due, prefixes = [], [], [], []
            for value in batch.column(1):
                h = shingle_hashes(value.as_py(), words)
                n = len(h)
                sizes.append(n)
                digests.append(_digest(h) if n else None)
                due.append(required(n, percent) if n else 0)
                prefixes.append(h[: n - least_overlap(n, percent) + 1 + slack(n, percent)].view(np.int64) if n else [])
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(sizes, pa.int64()), pa.array(digests, pa.binary()), pa.array(due, pa.int32()), pa.array(prefixes, pa.list_(pa.int64()))], ["doc_id", "n_shingles", "digest", "due", "prefix"])

    return kernel


def _set_kernel(words: int):
    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep, sets = [], []
            for i, (value, digest) in enumerate(zip(batch.column(0), batch.column(1).to_pylist(), strict=True)):
                h = shingle_hashes(value.as_py(), words)
                if _digest(h) == digest:  # a doc_id may have several texts
                    keep.append(i)
                    sets.append(h.tobytes())
            rest = batch.take(pa.array(keep, pa.int64()))
            yield pa.RecordBatch.from_arrays([rest.column(1), rest.column(2), pa.array(sets, pa.binary())], ["digest", "tasks", "shingles"])

    return kernel


def merge_skip(lists: list[np.ndarray], need: int) -> Iterator[tuple[int, int]]:
    """(entry, lists that hold it), ascending, of the entries in `need` of the sorted lists at least.

    The lists' heads lie in a heap. An entry on too few heads is left together with the next smallest heads,
    need - 1 lists in all, and these lists jump by binary search to the entry that the others have reached.
    """
    heap = [(int(x[0]), i) for i, x in enumerate(lists) if len(x)]
    heapq.heapify(heap)
    at = [0] * len(lists)
    while len(heap) >= need:
        least, popped = heap[0][0], []
        while heap and heap[0][0] == least:
            popped.append(heapq.heappop(heap)[1])
        if len(popped) >= need:
            yield least, len(popped)
            onward = least + 1
        else:
            while heap and len(popped) < need - 1:
                popped.append(heapq.heappop(heap)[1])
            if not heap:
                return
            onward = heap[0][0]
        for i in popped:
            x = lists[i]
            if x[at[i]] < onward:
                at[i] += 1
            if at[i] < len(x) and x[at[i]] < onward:
                at[i] += int(np.searchsorted(x[at[i] :], onward))
            if at[i] < len(x):
                heapq.heappush(heap, (int(x[at[i]]), i))


class OccurrenceSearch:
    """Links among the documents of one task. sets: sorted uint64 arrays; sides: links within one side are skipped if across.

    Documents are numbered by size; each shingle that two of them have is an inverted list of numbers. Of the T
    shingles that a document must share with a partner of its size or less, L may lie in its L longest lists: the
    others are merged for T - L occurrences, and a candidate is looked up in the long ones by binary search.
    """

    def __init__(self, sets: list[np.ndarray], percent: int, sides: list[int] | None = None):
        self.percent = percent
        self.order = sorted(range(len(sets)), key=lambda i: (len(sets[i]), i))
        self.sides = np.array([sides[i] for i in self.order]) if sides else None
        sizes = [len(sets[i]) for i in self.order]
        self.size = np.array(sizes, dtype=np.int64)
        every = np.concatenate([sets[i] for i in self.order]) if sets else np.empty(0, np.uint64)
        place = np.argsort(every, kind="stable")  # by shingle, and by document within
        ranked = every[place]
        code = np.zeros(len(every), dtype=np.int32)
        np.cumsum(ranked[1:] != ranked[:-1], out=code[1:])
        del every, ranked
        self.length = np.bincount(code).astype(np.int32)
        shared = self.length[code] > 1  # a shingle that one document holds joins nothing
        owner = np.repeat(np.arange(len(sizes), dtype=np.int32), sizes)
        self.postings = owner[place[shared]]
        self.first = np.concatenate(([0], np.cumsum(np.where(self.length > 1, self.length, 0)))) if len(code) else np.zeros(1, np.int64)
        by_place, kept = np.empty_like(code), np.empty(len(code), dtype=bool)
        by_place[place], kept[place] = code, shared
        del place, code, shared
        ends = np.concatenate(([0], np.cumsum(np.bincount(owner[kept], minlength=len(sizes))))) if len(sizes) else np.zeros(1, np.int64)
        by_place = by_place[kept]
        self.codes = [by_place[ends[i] : ends[i + 1]] for i in range(len(sizes))]
        self.label = np.arange(len(sizes))  # the component of each document
        self.members = [[i] for i in range(len(sizes))]

    def _join(self, a: int, b: int) -> None:
        a, b = self.label[a], self.label[b]
        if len(self.members[a]) < len(self.members[b]):
            a, b = b, a
        self.label[self.members[b]] = a
        self.members[a] += self.members[b]
        self.members[b] = []

    def probe(self, lists: np.ndarray, entry: int) -> int:
        """How many of the lists hold the entry: a binary search in each, step by step in all of them."""
        lo, end = self.first[lists], self.first[lists + 1]
        hi = end.copy()
        for _ in range(int(self.length[lists].max(initial=0)).bit_length()):
            middle = (lo + hi) >> 1
            below = (lo < hi) & (self.postings[np.minimum(middle, len(self.postings) - 1)] < entry)
            lo, hi = np.where(below, middle + 1, lo), np.where(below, hi, middle)
        return int(np.count_nonzero(self.postings[np.minimum(lo, len(self.postings) - 1)][lo < end] == entry))

    def links(self) -> Iterator[tuple[int, int]]:
        """Links that join what none before has joined; the components are those of all links."""
        for x, codes in enumerate(self.codes):
            n = int(self.size[x])
            due = least_overlap(n, self.percent)  # partners before x in the order are not larger
            if len(codes) < due:
                continue
            codes = codes[np.argsort(self.length[codes], kind="stable")]
            n_long = min(due - 1, int(due / (1 + LONG_SHARE * np.log2(self.length[codes[-1]]))))
            need = due - n_long
            short, long = codes[: len(codes) - n_long], codes[len(codes) - n_long :]
            least = int(np.searchsorted(self.size, -(-self.percent * n // 100)))  # smaller ones share too little
            entries, counts = self._merge(short, need, least, x)
            # The unknown long lists can add n_long at most.
            most = counts + n_long
            can = 100 * most >= self.percent * (n + self.size[entries] - most)
            if self.sides is not None:
                can &= self.sides[entries] != self.sides[x]
            entries, counts = entries[can], counts[can]
            order = np.argsort(-counts, kind="stable")
            entries, counts = entries[order], counts[order]
            while len(entries):
                y, both = int(entries[0]), int(counts[0]) + self.probe(long, int(entries[0]))
                entries, counts = entries[1:], counts[1:]
                if 100 * both >= self.percent * (n + int(self.size[y]) - both):
                    self._join(x, y)
                    yield self.order[x], self.order[y]
                    apart = self.label[entries] != self.label[x]  # what x reaches now needs no look-up
                    entries, counts = entries[apart], counts[apart]
                elif len(entries) * PROBE_COST > int(self.length[long].sum()):
                    # So many candidates that merging the long lists too is less than a probe for each.
                    held, more = self._merge(long, 1, least, x)
                    at = np.minimum(np.searchsorted(held, entries), max(len(held) - 1, 0))
                    total = counts + (np.where(held[at] == entries, more[at], 0) if len(held) else 0)
                    linked = 100 * total >= self.percent * (n + self.size[entries] - total)
                    for z in entries[linked].tolist():
                        if self.label[z] != self.label[x]:
                            self._join(x, z)
                            yield self.order[x], self.order[z]
                    break

    def _merge(self, codes: np.ndarray, need: int, least: int, x: int) -> tuple[np.ndarray, np.ndarray]:
        """(entries from least to x, ascending; their counts) in `need` lists at least.

        Few postings go through the heap; many are counted in one array.
        """
        lists = [self.postings[self.first[c] : self.first[c + 1]] for c in codes.tolist()]
        if sum(map(len, lists)) <= HEAP_MOST:
            lists = [y[np.searchsorted(y, least) : np.searchsorted(y, x)] for y in lists]
            found = list(merge_skip(lists, need))
            return np.array([e for e, _ in found], dtype=np.int64), np.array([c for _, c in found], dtype=np.int64)
        merged = np.concatenate(lists)
        merged = merged[(merged >= least) & (merged < x)]
        if len(merged) * 8 < x - least:
            entries, counts = np.unique(merged, return_counts=True)
        else:
            counts = np.bincount(merged - least, minlength=1)
            entries = np.arange(least, least + len(counts))
        enough = counts >= need
        return entries[enough].astype(np.int64), counts[enough]


def _link_kernel(percent: int):
    def kernel(table: pa.Table) -> pa.Table:
        digests = table["digest"].to_pylist()
        sets = [np.frombuffer(x.as_py(), np.uint64) for x in table["shingles"]]
        sides = table["block"].to_pylist()
        across = table["i"][0].as_py() != table["j"][0].as_py()
        pairs = [(digests[a], digests[b]) for a, b in OccurrenceSearch(sets, percent, sides if across else None).links()]
        return pa.table({"src": pa.array([a for a, _ in pairs], pa.binary()), "dst": pa.array([b for _, b in pairs], pa.binary())})

    return kernel


_TASKS = "array<struct<pool:long,whole:long,i:long,j:long,block:long>>"


def tasks_of(chosen: DataFrame, total: int, percent: int) -> DataFrame:
    """chosen: (doc_id, digest, n, root) -> (doc_id, digest, tasks). Small clusters share a pool; a large one is cut
    into blocks by set size, and each pair of blocks whose sizes permit a link is a task of its own.

    Sums run over one row for each set size of a cluster; a size that fills several blocks is dealt on by hash.
    """
    pools = max(1, -(-total // TASK_SHINGLES))
    over = chosen.groupBy("root").agg(F.sum("n").alias("all")).where(F.col("all") > TASK_SHINGLES).select("root")
    by_size = chosen.join(over, "root", "left_semi").groupBy("root", "n").agg(F.sum("n").alias("held"))
    upto = F.sum("held").over(Window.partitionBy("root").orderBy("n").rowsBetween(Window.unboundedPreceding, 0))
    places = by_size.select("root", "n", F.floor((upto - F.col("held")) / TASK_SHINGLES).alias("place"), F.greatest(F.lit(1), F.floor(F.col("held") / TASK_SHINGLES)).alias("parts"))
    cut = chosen.join(places, ["root", "n"], "left").select("doc_id", "digest", "n", "root", (F.col("place") + F.pmod(F.xxhash64("digest"), F.col("parts"))).alias("block"))
    cut = materialise(cut, "join-cut")
    zero = F.lit(0).cast("long")
    pool = F.pmod(F.xxhash64("root"), F.lit(pools)).cast("long")
    small = cut.where("block is null").select("doc_id", "digest", F.array(F.struct(pool.alias("pool"), F.lit(None).cast("long").alias("whole"), zero.alias("i"), zero.alias("j"), zero.alias("block"))).alias("tasks"))
    large = cut.where("block is not null")
    blocks = large.groupBy("root", "block").agg(F.min("n").alias("lo"), F.max("n").alias("hi"))
    left = blocks.select("root", F.col("block").alias("i"), F.col("lo").alias("lo_i"), F.col("hi").alias("hi_i"))
    right = blocks.select("root", F.col("block").alias("j"), F.col("lo").alias("lo_j"), F.col("hi").alias("hi_j"))
    fit = (F.col("hi_i") * 100 >= F.col("lo_j") * percent) & (F.col("hi_j") * 100 >= F.col("lo_i") * percent)
    pairs = left.join(right, "root").where((F.col("i") <= F.col("j")) & fit)
    ends = pairs.select("root", "i", "j", F.explode(F.array_distinct(F.array("i", "j"))).alias("block"))
    task = F.struct(F.lit(-1).cast("long").alias("pool"), F.col("root").alias("whole"), "i", "j", "block")
    by_block = ends.groupBy("root", "block").agg(F.collect_list(task).alias("tasks"))
    return small.unionByName(large.join(by_block, ["root", "block"]).select("doc_id", "digest", "tasks"))


def _hot(rows: DataFrame) -> list[int]:
    """Shingles of very many keys, as one in HOT_IN keys shows them: HOT_MOST at most, and a hint for dealing alone."""
    some = rows.where(F.pmod(F.xxhash64("key", F.lit(3)), F.lit(HOT_IN)) == 0)
    held = some.groupBy("shingle").agg(F.count("*").alias("held")).where(F.col("held") >= HOT_HELD)
    return sorted(r.shingle for r in held.orderBy(F.desc("held"), "shingle").limit(HOT_MOST).collect())


def _in_two(rows: DataFrame, hot: list[int]) -> DataFrame:
    """(key, due, shingle, head): the rows whose shingle another key has too, with the least key that has it.

    Rows of hot shingles stay where they are, with a node that stands for the shingle; the others are dealt by shingle.
    """
    by_shingle = Window.partitionBy("shingle")
    crowd = F.col("shingle").isin(hot)
    spread = rows.where(~crowd) if hot else rows
    spread = spread.select("key", "due", "shingle", F.min("key").over(by_shingle).alias("head"), F.max("key").over(by_shingle).alias("last")).where("head < last").drop("last")
    return spread.union(rows.where(crowd).select("key", "due", "shingle", F.xxhash64("shingle").alias("head"))) if hot else spread


def _edges(shared: DataFrame, hot: list[int]) -> DataFrame:
    """(src, dst) of the cluster graph. A key hangs on one of its hot shingles; these are joined by the distinct sets of them."""
    edge = lambda a, b: ((F.col(a) if isinstance(a, str) else a).alias("src"), (F.col(b) if isinstance(b, str) else b).alias("dst"))
    if not hot:
        return shared.select(*edge("head", "key"))
    crowd = F.col("shingle").isin(hot)
    held = shared.where(crowd).groupBy("key").agg(F.array_sort(F.collect_set("head")).alias("heads"))  # HOT_MOST at most
    least = F.element_at("heads", 1)
    return shared.where(~crowd).select(*edge("head", "key")).union(held.select(*edge(least, "key"))).union(held.select("heads").distinct().select(*edge(least, F.explode("heads"))))


def jaccard_components(docs: DataFrame, words: int = WORDS, percent: int = PERCENT) -> DataFrame:
    """Per row of docs: doc_id, n_shingles, component_id (the smallest doc_id that links reach).

    A null, empty or blank text has no shingle, links with nothing and is its own component. A text of fewer
    words is one shingle. Rows with equal sets are linked; a doc_id that is repeated with another text takes
    part with each text. An empty table gives no rows, other columns are ignored, texts are read whole.
    """
    spark = docs.sparkSession
    ship(spark)
    rows = texts(docs)
    prefixes = materialise(rows.mapInArrow(giving_back(_prefix_kernel(words, percent)), "doc_id long, n_shingles long, digest binary, due int, prefix array<long>"), "join-prefixes")
    held = prefixes.where("n_shingles > 0")
    classes = materialise(held.groupBy("digest").agg(F.min("doc_id").alias("first_id"), F.min("n_shingles").alias("n"), F.count("*").alias("copies")), "join-classes")
    # One row of each class stands for it; its key in the cluster graph is short, a clash there would only merge clusters.
    key = F.xxhash64("digest")
    one = held.select("digest", "doc_id", "due", "prefix").join(classes.select("digest", F.col("first_id").alias("doc_id")), ["digest", "doc_id"], "left_semi")
    short = one.select(key.alias("key"), "due", F.explode("prefix").alias("shingle"))
    hot = _hot(short)
    shared = materialise(_in_two(short, hot), "join-shared")
    named = materialise(prefixes.select("doc_id", "n_shingles", "digest"), "join-named")
    discard(prefixes)
    of_key = F.count("*").over(Window.partitionBy("key"))
    for _ in range(PRUNING_ROUNDS):  # who goes may leave others with too few
        enough = shared.select("key", "due", "shingle", of_key.alias("n")).where("n >= due").drop("n")
        older, shared = shared, materialise(_in_two(enough, hot), "join-shared")
        discard(older)
    clusters = components(_edges(shared, hot))
    chosen = materialise(classes.withColumn("node", key).join(clusters, "node").select(F.col("first_id").alias("doc_id"), "digest", "n", "root"), "join-chosen")
    discard(shared)
    total, many = chosen.agg(F.coalesce(F.sum("n"), F.lit(0)), F.count("*")).first()
    dealt = tasks_of(chosen, total, percent)
    small = many <= BROADCAST_ROWS  # about 100 bytes a row; beyond that both sides are dealt by doc_id
    with_text = rows.join(F.broadcast(dealt) if small else dealt, "doc_id").select("text", "digest", "tasks")
    sets = with_text.mapInArrow(giving_back(_set_kernel(words)), f"digest binary, tasks {_TASKS}, shingles binary").select("digest", "shingles", F.explode("tasks").alias("t")).select("digest", "shingles", "t.*")
    links = components(sets.groupBy("pool", "whole", "i", "j").applyInArrow(_link_kernel(percent), "src binary, dst binary"))
    linked = classes.join(links.select(F.col("node").alias("digest"), "root"), "digest", "left").select("digest", "first_id", F.coalesce("root", "digest").alias("root"), F.col("root").isNotNull().alias("linked"), "copies")
    least = linked.where("linked").groupBy("root").agg(F.min("first_id").alias("least"))
    # Only classes of several rows or with links need their name looked up.
    names = linked.where("linked or copies > 1").join(least, "root", "left").select("digest", F.coalesce("least", "first_id").alias("component_id"))
    out = named.join(names, "digest", "left")
    return out.select("doc_id", "n_shingles", F.coalesce("component_id", "doc_id").alias("component_id"))


def op7_occurrence_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_components(read(spark, sf_dir, "documents"))
