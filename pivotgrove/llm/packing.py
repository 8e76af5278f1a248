"""Operator 3: concatenate documents' tokens and cut them into fixed windows.

The documents are put in order of doc_id and text hash, so that the same rows give the same pieces however they lie.
Pass one tokenises each partition and writes its documents with the tokens before each inside the partition.
The totals of the partitions, one row each, give every partition's place by a prefix sum; partition place
and local place together are the global offset. Pass two cuts at the multiples of the window: a document
that crosses one gives a boundary record for each window it touches. Only the last window is not full.
"""

from __future__ import annotations

import functools
import re
from array import array
from collections.abc import Iterator
from itertools import chain

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from pivotgrove.llm.tables import read, texts, vocabulary
from pivotgrove.runtime import giving_back, materialise, ship

VOCABULARY = "word_bpe_49k.json"
WINDOW, END_ID = 2048, 1
MEMO_ENTRIES = 600_000


_LATIN = "a-z\u00df-\u00f6\u00f8-\u017f"
_PLAIN = re.compile("[!-;=-~\u00c0-\u00d6\u00d8-\u00f6\u00f8-\u012f\u0131-\u0148\u014a-\u017f]+").fullmatch
#: Fixed value: the vocabulary's own pattern, for the characters of a plain word.
_RUNS = re.compile(f"'s|'t|'re|'ve|'m|'ll|'d|[{_LATIN}]+|[0-9]|[^{_LATIN}0-9]+").findall


class WordTokenizer:
    """Whole texts by words: the vocabulary drops white space and its pattern never crosses it.

    A word of plain Latin characters is lower-cased and cut into runs here, and the library's merges are asked
    once for each run; any other word is asked of the library as it is, and so is a text with a control
    character that Python takes as white space and the library does not. Words and runs are kept up to a bound.
    """

    def __init__(self, vocabulary_file: str, memo_entries: int = MEMO_ENTRIES):
        from tokenizers import Tokenizer, pre_tokenizers

        self.library = Tokenizer.from_file(vocabulary_file)
        self.model = self.library.model
        self.memo_entries = memo_entries
        self.memo: dict[str, bytes] = {}
        self.runs: dict[str, bytes] = {}
        mapped = pre_tokenizers.ByteLevel(add_prefix_space=False, use_regex=False)
        #: The library's letters for the bytes of a character.
        self.letters = {c: mapped.pre_tokenize_str(chr(c))[0][0] for c in range(33, 0x180) if not 127 <= c < 161}
        self.letters = {c: x if c < 128 else x[-2:] for c, x in self.letters.items()}

    def _whole(self, text: str) -> bytes:
        return array("I", self.library.encode(text, add_special_tokens=False).ids).tobytes()

    def _learn(self, word: str) -> bytes:
        if not _PLAIN(word):
            return self._whole(word)
        out = []
        for run in _RUNS(word.lower()):
            found = self.runs.get(run)
            if found is None:
                found = self.runs[run] = array("I", [t.id for t in self.model.tokenize(run.translate(self.letters))]).tobytes()
            out.append(found)
        return b"".join(out)

    def encode_packed(self, texts: list[str]) -> list[bytes]:
        """Little-endian unsigned 32-bit ids of each text."""
        for kept in (self.memo, self.runs):
            if len(kept) > self.memo_entries:
                kept.clear()
        plain = [None if "\x1c" in t or "\x1d" in t or "\x1e" in t or "\x1f" in t else t.split() for t in texts]
        for word in set(chain.from_iterable(w for w in plain if w)).difference(self.memo):
            self.memo[word] = self._learn(word)
        look = self.memo.__getitem__
        return [self._whole(t) if w is None else b"".join(map(look, w)) for t, w in zip(texts, plain, strict=True)]


@functools.lru_cache(maxsize=2)
def tokenizer(vocabulary_file: str) -> WordTokenizer:
    import os

    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    return WordTokenizer(vocabulary_file)


def tokenise(docs: DataFrame, vocabulary_file: str | None = None, end_id: int = END_ID) -> DataFrame:
    """(part, local_start, doc_id, doc_tokens, ids): the partitions' documents in order, each with its end id."""
    ship(docs.sparkSession)
    place = vocabulary_file or vocabulary(VOCABULARY)
    end = end_id.to_bytes(4, "little")

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own, part, before = tokenizer(place), TaskContext.get().partitionId(), 0
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                rows = batch.slice(at, 256)
                packed = [p + end for p in own.encode_packed(rows.column(1).to_pylist())]
                counts = [len(p) // 4 for p in packed]
                starts = []
                for n in counts:
                    starts.append(before)
                    before += n
                yield pa.RecordBatch.from_pydict({"part": [part] * len(counts), "local_start": starts, "doc_id": rows.column(0), "doc_tokens": counts, "ids": packed})

    rows = texts(docs).withColumn("h", F.xxhash64("text")).repartitionByRange("doc_id", "h").sortWithinPartitions("doc_id", "h").drop("h")
    return rows.mapInArrow(giving_back(kernel), "part long, local_start long, doc_id long, doc_tokens long, ids binary")


def pack(docs: DataFrame, window: int = WINDOW, vocabulary_file: str | None = None, end_id: int = END_ID, keep_ids: bool = False) -> DataFrame:
    """Per piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset, and with keep_ids the packed ids.

    A null or empty text is the end id alone. Repeated rows and ids are packed each for itself, null ids first; an empty table
    gives no rows, other columns are ignored; a document longer than the window gives a piece for each window.
    """
    tokens = materialise(tokenise(docs, vocabulary_file, end_id), "packing-tokens")
    totals = tokens.groupBy("part").agg(F.sum("doc_tokens").alias("total"))  # one row for each partition of the input
    place = totals.select("part", (F.sum("total").over(Window.orderBy("part")) - F.col("total")).alias("place"))
    first = (F.col("place") + F.col("local_start")).alias("first")
    placed = tokens.join(F.broadcast(place), "part").select("doc_id", "doc_tokens", "ids", first)
    last = F.col("first") + F.col("doc_tokens") - 1
    pieces = placed.withColumn("sequence_id", F.explode(F.sequence(F.floor(F.col("first") / window), F.floor(last / window))))
    begin = F.greatest(F.col("first"), F.col("sequence_id") * window)
    end = F.least(last + 1, (F.col("sequence_id") + 1) * window)
    pieces = pieces.select("doc_id", (begin - F.col("first")).alias("start"), (end - begin).alias("length"), "doc_tokens", "sequence_id", (begin - F.col("sequence_id") * window).alias("offset"), "ids")
    cut = F.substring("ids", (F.col("start") * 4 + 1).cast("int"), (F.col("length") * 4).cast("int"))
    return pieces.select("doc_id", "start", "length", F.crc32(cut).alias("ids_crc32"), "doc_tokens", "sequence_id", "offset", *([cut.alias("ids")] if keep_ids else []))


def op3_concatenate_and_cut(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(read(spark, sf_dir, "documents"))
