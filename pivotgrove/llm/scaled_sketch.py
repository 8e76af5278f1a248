"""Operator 10: document fingerprints by a threshold-scaled sketch.

Of the hashes of a text's word shingles all those below a fixed fraction of the hash range are kept. The
sketch of a union is the union of the sketches, its size follows the text's, and the share of one sketch in
another estimates containment however unequal the texts are. A text of few shingles keeps them all, and is cut
to the fraction when it meets a larger one. A fingerprint is written as the number of distinct shingles, a
digest of all of them, and 32 bits of each kept hash in ascending order.

Each document is also set against its edited text, which takes the next document's beginning. One range
exchange by doc_id brings neighbours together; where a partition ends, its last document and the first of
the next partition that has any are written as boundary records and meet in a small second step.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from pivotgrove.llm.shingles import shingle_hashes
from pivotgrove.llm.tables import read, texts
from pivotgrove.runtime import materialise, ship

WORDS, SCALE = 5, 8  #: words in a shingle; one hash in SCALE is kept
WHOLE = 64  #: up to so many shingles a text keeps all
_CUT = np.uint32((1 << 32) // SCALE)
_MERGED_WHOLE, _MERGED = (1 << 64) - 1, (1 << 64) - 2  #: stand for the total of a merged sketch


class Sketch:
    """The kept hashes (ascending), how many shingles they were drawn from, and the sum of all as a digest.

    A merged sketch knows its kept hashes alone: total and digest are those of a text, and then unknown.
    """

    def __init__(self, total: int, digest: int, kept: np.ndarray):
        self.total, self.digest, self.kept = total, digest, kept

    @classmethod
    def of(cls, text: str, words: int = WORDS) -> Sketch:
        return cls.over(shingle_hashes(text, words))

    @classmethod
    def over(cls, hashes: np.ndarray) -> Sketch:
        """Of a set of distinct 64-bit shingle hashes."""
        digest = int(hashes.sum(dtype=np.uint64)) if len(hashes) else 0
        kept = np.unique((hashes >> np.uint64(32)).astype(np.uint32))  # 32 bits are kept of each
        return cls(len(hashes), digest, kept if len(hashes) <= WHOLE else kept[kept < _CUT])

    @property
    def whole(self) -> bool:
        """Every shingle was kept."""
        return self.total <= WHOLE or self.total == _MERGED_WHOLE

    def _alike(self, other: Sketch) -> tuple[np.ndarray, np.ndarray]:
        """Both sketches' hashes under one fraction."""
        if self.whole and other.whole:
            return self.kept, other.kept
        return self.kept[self.kept < _CUT], other.kept[other.kept < _CUT]

    def merge(self, other: Sketch) -> Sketch:
        """The sketch of both texts' shingles together."""
        a, b = self._alike(other)
        kept = np.union1d(a, b)
        whole = self.whole and other.whole and len(kept) <= WHOLE
        return Sketch(_MERGED_WHOLE, 0, kept) if whole else Sketch(_MERGED, 0, kept[kept < _CUT])

    def containment(self, other: Sketch) -> float:
        """Estimated share of this text's shingles that the other has; 0 where nothing was kept."""
        if self._same(other):
            return 1.0
        a, b = self._alike(other)
        return len(np.intersect1d(a, b, assume_unique=True)) / len(a) if len(a) else 0.0

    def _same(self, other: Sketch) -> bool:
        return self.total < _MERGED and (self.total, self.digest) == (other.total, other.digest)

    def likeness(self, other: Sketch) -> float:
        """Estimated Jaccard similarity; texts with the same shingles have 1, whatever was kept of them."""
        if self._same(other):
            return 1.0
        a, b = self._alike(other)
        both = len(np.intersect1d(a, b, assume_unique=True))
        union = len(a) + len(b) - both
        return both / union if union else 0.0

    def __bytes__(self) -> bytes:
        return self.total.to_bytes(8, "big") + self.digest.to_bytes(8, "big") + self.kept.astype(">u4").tobytes()

    def __str__(self) -> str:
        return bytes(self).hex()

    @classmethod
    def parse(cls, written: str) -> Sketch:
        raw = bytes.fromhex(written)
        return cls(int.from_bytes(raw[:8], "big"), int.from_bytes(raw[8:16], "big"), np.frombuffer(raw[16:], ">u4").astype(np.uint32))


def edited(text: str, following: str) -> str:
    half = len(text) // 2
    return text[: len(text) - half] + following[:half]


def _row(text: str, own: Sketch, following: str, nxt: Sketch) -> tuple:
    changed = edited(text, following)
    other = own if changed == text else Sketch.of(changed)
    return len(text), hashlib.sha256(changed.encode()).digest(), bytes(own), bytes(other), own.likeness(other), own.likeness(nxt), own.containment(other), own.containment(nxt)


_RESULT = "n_chars long, edited_sha256 binary, fingerprint binary, edited_fingerprint binary, near_edited double, near_next double, in_edited double, in_next double"
_NAMES = [x.split()[0] for x in _RESULT.split(", ")]


def _neighbours(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows of a sorted partition; the first one's text and the last one's text go out as boundary records."""
    part, held = TaskContext.get().partitionId(), None

    def written(rows: list[tuple]) -> pa.RecordBatch:
        kinds = [pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64(), pa.binary(), pa.binary(), pa.binary(), *[pa.float64()] * 4]
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), kinds, strict=True)], ["part", "doc_id", "head", "tail", *_NAMES])

    for batch in batches:
        rows = []
        for doc_id, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
            text = text.as_py()
            own = Sketch.of(text)
            if held is None:
                rows.append((part, None, text, None, *[None] * len(_NAMES)))
            else:
                rows.append((part, held[0], None, None, *_row(held[1], held[2], text, own)))
            held = (doc_id, text, own)
        if rows:
            yield written(rows)
    if held is not None:
        yield written([(part, held[0], None, held[1], *[None] * len(_NAMES))])


def _boundaries(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        got = []
        for text, following in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist(), strict=True):
            got.append(_row(text, Sketch.of(text), following, Sketch.of(following)))
        if got:
            yield pa.RecordBatch.from_arrays([batch.column(0), *[pa.array(c) for c in zip(*got, strict=True)]], ["doc_id", *_NAMES])


def fingerprints(docs: DataFrame) -> DataFrame:
    """Per row of docs: doc_id, the columns of the contract, and in_edited and in_next: the shares of its shingles there.

    A null text counts as empty: no shingle, likeness 1 to another empty text and 0 to any other. A text of
    fewer words than a shingle is one shingle. The order is (doc_id, hash of the text): repeated ids and rows follow one
    another; a single row follows itself; an empty table gives no rows; other columns are ignored.
    """
    ship(docs.sparkSession)
    ordered = texts(docs).withColumn("h", F.xxhash64("text")).repartitionByRange("doc_id", "h").sortWithinPartitions("doc_id", "h").drop("h")
    found = materialise(ordered.mapInArrow(_neighbours, f"part long, doc_id long, head string, tail string, {_RESULT}"), "sketch-rows")
    heads = found.where("head is not null").select("part")
    # Partitions are few and carry numbers alone here: each is given the next one that has rows, the last the first.
    by_part = Window.orderBy("part")
    follow = heads.select("part", F.coalesce(F.lead("part").over(by_part), F.min("part").over(Window.partitionBy())).alias("next_part"))
    last = found.where("tail is not null").select("part", "doc_id", "tail").join(follow, "part")
    pairs = last.join(found.where("head is not null").select(F.col("part").alias("next_part"), "head"), "next_part").select("doc_id", "tail", "head")
    out = found.where("n_chars is not null").select("doc_id", *_NAMES).union(pairs.mapInArrow(_boundaries, f"doc_id long, {_RESULT}"))
    return out.withColumns({c: F.lower(F.hex(c)) for c in ("edited_sha256", "fingerprint", "edited_fingerprint")})


def op10_scaled_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fingerprints(read(spark, sf_dir, "documents"))
