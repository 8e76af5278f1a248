"""Operator 6: toxicity by a factorisation machine over hashed terms.

A document is the set of its hashed words. The machine's score is a bias, a weight for each term and, for
each pair of terms present, the product of two short vectors: a word that is harmless alone can count beside
another, which no sum of weights can say. Every term of the labelled rows has a weight, which an L1 penalty
holds at nought until enough rows speak for it; every term that enough rows have, whatever their labels, has a
vector. Pairs count by the mean over a document's vectors, so that long documents are not learned by heart.

Labels are learned from a bounded sample of the labelled rows (least hash first, so the sample is the same
whatever the partitioning); the model is a few arrays of bounded size and goes to every task.
"""

from __future__ import annotations

import re
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pivotgrove.llm.tables import read, texts
from pivotgrove.runtime import giving_back, ship

BITS, FACTORS = 20, 8
MAX_LABELLED = 20_000  #: rows that the model is fitted on at most
SUPPORT_ROWS, SUPPORT_SHARE = 20, 0.01  #: a term has a vector from so many rows and from this share of them on
EPOCHS, SEED = 6, 7
RATE, L1, L2 = 1.0, 15.0, 1.0  #: of the weights
PAIR_START, PAIR_RATE, PAIR_L2 = 0.2, 0.3, 1e-3  #: of the vectors
SURE = 0.01  #: a row that is off by less moves nothing
NOTHING_KNOWN = -4.0  #: the bias without a labelled row: no document is called toxic
_WORD = re.compile(rb"[a-z\x80-\xff]+")
_TERMS_KEPT = 500_000


def terms(text: str) -> set[bytes]:
    """The distinct words of a whole text, lower-cased."""
    return set(_WORD.findall(text.lower().encode()))


def hashed(word: bytes) -> int:
    return zlib.crc32(word) & ((1 << BITS) - 1)


def _squash(z):
    return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


@dataclass
class FactorisationMachine:
    """slot: from a term's hash to its row in weight and factor; a term without a vector has a row of noughts."""

    bias: float
    slot: dict[int, int]
    weight: np.ndarray
    factor: np.ndarray

    @classmethod
    def over(cls, rows: list[np.ndarray], factors: int = FACTORS, seed: int = SEED) -> FactorisationMachine:
        """An untrained machine with a slot for every term hash of the rows."""
        found, count = np.unique(np.concatenate(rows), return_counts=True) if rows else (np.empty(0, int), np.empty(0, int))
        factor = np.random.default_rng(seed).normal(0, PAIR_START, (len(found), factors))
        factor[count < max(SUPPORT_ROWS, SUPPORT_SHARE * len(rows))] = 0
        return cls(NOTHING_KNOWN, {int(h): i for i, h in enumerate(found)}, np.zeros(len(found)), factor)

    def slots(self, words: set[bytes], memo: dict[bytes, int]) -> np.ndarray:
        """The known terms of a document; memo keeps the words that were met."""
        if len(memo) > _TERMS_KEPT:
            memo.clear()
        out = set()
        for w in words:
            at = memo.get(w)
            if at is None:
                at = memo[w] = self.slot.get(hashed(w), -1)
            out.add(at)
        out.discard(-1)
        return np.sort(np.fromiter(out, np.int64, len(out)))

    def margin(self, x: np.ndarray) -> float:
        v = self.factor[x]
        held = int(np.count_nonzero(v.any(axis=1)))
        total = v.sum(0)
        return self.bias + float(self.weight[x].sum()) + 0.5 * float(total @ total - (v * v).sum()) / max(held, 1)

    def fit(self, rows: list[np.ndarray], labels: np.ndarray, epochs: int = EPOCHS, seed: int = SEED, pairs: bool = True) -> FactorisationMachine:
        """Passes over single rows in a drawn order: proximal steps for weights, Adagrad for vectors.

        A class weighs by the inverse root of its share. Without pairs the vectors are left out: a linear model.
        """
        if not len(rows):
            return self
        draw = np.random.default_rng(seed)
        share = min(max(float(np.mean(labels)), 1e-6), 1 - 1e-6)
        worth = (np.sqrt(0.5 / (1 - share)), np.sqrt(0.5 / share))
        self.bias, bias_square = float(np.log(share / (1 - share))), 1.0
        if not pairs:
            self.factor[:] = 0
        has = self.factor.any(axis=1)
        rows = [np.array([self.slot[h] for h in x.tolist() if h in self.slot], dtype=np.int64) for x in rows]
        paired = [x[has[x]] for x in rows]
        pull, square, pair_square = np.zeros(len(has)), np.zeros(len(has)), np.ones(len(has))
        for _ in range(epochs):
            for i in draw.permutation(len(rows)):
                x, f = rows[i], paired[i]
                v = self.factor[f]
                total, each = v.sum(0), 1 / max(len(f), 1)
                z = self.bias + self.weight[x].sum() + 0.5 * each * (total @ total - (v * v).sum())
                gap = float((_squash(z) - labels[i]) * worth[int(labels[i])])
                if abs(gap) < SURE:
                    continue
                bias_square += gap * gap
                self.bias -= 0.1 * gap / np.sqrt(bias_square)
                before = square[x]
                after = before + gap * gap
                root = np.sqrt(after)
                q = pull[x] + gap - (root - np.sqrt(before)) / RATE * self.weight[x]
                pull[x], square[x] = q, after
                self.weight[x] = np.where(np.abs(q) <= L1, 0.0, (np.sign(q) * L1 - q) / (root / RATE + L2))
                if len(f) > 1:
                    g = gap * each * (total - v) + PAIR_L2 * v
                    pair_square[f] += (g * g).sum(1)
                    self.factor[f] = v - PAIR_RATE * g / np.sqrt(pair_square[f])[:, None]
        return self

    def compact(self) -> FactorisationMachine:
        """The same machine without the terms that change no score."""
        used = np.flatnonzero((self.weight != 0) | self.factor.any(axis=1))
        place = {int(i): n for n, i in enumerate(used)}
        return FactorisationMachine(self.bias, {h: place[i] for h, i in self.slot.items() if i in place}, self.weight[used], self.factor[used])


def _term_kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        found = [np.unique([hashed(w) for w in terms(v.as_py())]).astype(np.int32) for v in batch.column(1)]
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), pa.array(found, pa.list_(pa.int32()))], ["doc_id", "label", "terms"])


def fit(docs: DataFrame, labels: DataFrame, label: str = "toxic", max_labelled: int = MAX_LABELLED) -> FactorisationMachine:
    """Learn from rows with a label of 0 or 1 and crc32(doc_id as text) mod 5 other than 0.

    Rows without a label are not used; a doc_id labelled twice takes its greatest label. Without any row the
    machine is empty, every score is the same and under 0.5.
    """
    ship(docs.sparkSession)
    known = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col(label).cast("int").alias("label")).where(F.col("label").isin(0, 1) & (F.crc32(F.col("doc_id").cast("string")) % 5 != 0))
    known = known.groupBy("doc_id").agg(F.max("label").alias("label")).orderBy(F.xxhash64("doc_id"), "doc_id").limit(max_labelled)
    rows = texts(docs).join(F.broadcast(known), "doc_id").select("doc_id", "text", "label").mapInArrow(giving_back(_term_kernel), "doc_id long, label int, terms array<int>")
    got = rows.toArrow().sort_by([("doc_id", "ascending"), ("label", "ascending")])
    lists = got["terms"].combine_chunks()
    values = np.split(np.asarray(lists.flatten()), np.cumsum(np.asarray(lists.value_lengths()))[:-1]) if len(lists) else []
    known_labels = got["label"].to_numpy().astype(float)
    return FactorisationMachine.over(values).fit(values, known_labels).compact()


def score(docs: DataFrame, model: FactorisationMachine, keyed: bool = False) -> DataFrame:
    """Per row of docs: doc_id, held_out, score, predicted and, if keyed, row_key, the text's hash.

    A null or empty text gets the bias alone; a null doc_id is not held out.
    """
    ship(docs.sparkSession)
    shared = docs.sparkSession.sparkContext.broadcast((model.bias, model.slot, model.weight.astype(np.float32), model.factor.astype(np.float32)))

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own, memo = FactorisationMachine(*shared.value), {}
        for batch in batches:
            z = np.array([own.margin(own.slots(terms(v.as_py()), memo)) for v in batch.column(1)], dtype=float)
            p = _squash(z)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(p), *batch.columns[2:]], ["doc_id", "score", *batch.schema.names[2:]])

    held_out = F.coalesce(F.crc32(F.col("doc_id").cast("string")) % 5 == 0, F.lit(False))
    rows, key = texts(docs), ["row_key"] if keyed else []
    rows = rows.withColumn("row_key", F.xxhash64("text")) if keyed else rows
    scored = rows.mapInArrow(giving_back(kernel), "doc_id long, score double" + ", row_key long" * keyed)
    return scored.select("doc_id", held_out.alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"), *key)


def toxicity(docs: DataFrame, labels: DataFrame, label: str = "toxic") -> DataFrame:
    """Fit on the labelled rows and score all of docs: repeated rows get equal scores, empty tables give no rows."""
    return score(docs, fit(docs, labels, label))


def op6_factorisation_machine(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity(read(spark, sf_dir, "documents"), read(spark, sf_dir, "labels"))
