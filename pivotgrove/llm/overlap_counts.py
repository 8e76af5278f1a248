"""Operator 4: token counts of documents of any length by overlapping chunks that are spliced where they agree.

A long text is encoded in chunks that overlap. The cut between two chunks is put at a place in the overlap
that is proven stable and that both encodings have as a token boundary. Proven: no piece of the vocabulary
holds a word-start mark after another character (checked when the model is loaded), so no merge ever crosses
from a character into a following mark, whatever stands further away. Where an overlap has no such place, it
is widened, in the end to the rest of the text.
"""

from __future__ import annotations

import functools
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from pivotgrove.llm.tables import read, texts, vocabulary
from pivotgrove.runtime import ship

MODEL = "piece_bpe_32k.model"
CHUNK, OVERLAP, LIMIT = 4096, 96, 4096
_MARK = "▁"


class ChunkedEncoder:
    def __init__(self, model_file: str, chunk: int = CHUNK, overlap: int = OVERLAP):
        import sentencepiece

        self.model = sentencepiece.SentencePieceProcessor(model_file=model_file)
        self.chunk, self.overlap, self.widened = chunk, overlap, 0
        pieces = [self.model.id_to_piece(i) for i in range(self.model.get_piece_size())]
        #: Bytes of text that a token stands for; the mark stands for one space.
        self.width = [1 if self.model.is_byte(i) else len(p.replace(_MARK, " ").encode()) for i, p in enumerate(pieces)]
        self.provable = not any(re.search(f"[^{_MARK}]{_MARK}", p) for i, p in enumerate(pieces) if not self.model.is_control(i))
        probe = f" a{_MARK}b  c\té é 　ﬁ\n"
        self.provable &= self.model.decode(self.model.encode(probe)) == probe.replace(_MARK, " ")  # text is not rewritten

    def encode(self, text: str) -> list[int]:
        if len(text) <= self.chunk + self.overlap or not self.provable:
            return self.model.encode(text, num_threads=1)
        text = text.replace(_MARK, " ")  # the two are one symbol to the model
        out: list[int] = []
        start, kept_from = 0, 0  # this chunk's text begins at start; its tokens count from kept_from on
        while True:
            cut, end = self._cut(text, start + self.chunk)
            ids = self.model.encode(text[start:end], num_threads=1)
            head = self._tokens_before(ids, text, start, kept_from) if kept_from else 0
            if cut is None:
                return out + ids[head:]
            tail = self._tokens_after(ids, text, cut, end)
            if head is None or tail is None:  # the two sides do not agree there; not met with a provable vocabulary
                return self.model.encode(text, num_threads=1)
            out += ids[head : len(ids) - tail]
            kept_from, start = cut, max(cut - self.overlap, start + 1)

    def _cut(self, text: str, at: int) -> tuple[int | None, int]:
        """A stable place past `at` and the end of the chunk that holds it; the overlap doubles until there is one."""
        wide = self.overlap
        while at + wide < len(text):
            place = text.find(" ", at, at + wide)
            while 0 < place and text[place - 1] == " ":
                place = text.find(" ", place + 1, at + wide)
            if place > 0:
                return place, at + wide
            wide *= 2
            self.widened += 1
        return None, len(text)

    def _tokens_before(self, ids: list[int], text: str, start: int, place: int) -> int | None:
        due = 1 + len(text[start:place].encode())  # the model puts one mark before a text
        for n, token in enumerate(ids):
            if due <= 0:
                return n if due == 0 else None
            due -= self.width[token]
        return len(ids) if due == 0 else None

    def _tokens_after(self, ids: list[int], text: str, place: int, end: int) -> int | None:
        due, n = len(text[place:end].encode()), 0
        while due > 0:
            n += 1
            due -= self.width[ids[-n]]
        return n if due == 0 else None


@functools.lru_cache(maxsize=4)
def encoder(model_file: str, chunk: int, overlap: int) -> ChunkedEncoder:
    return ChunkedEncoder(model_file, chunk, overlap)


def count_tokens(docs: DataFrame, model_file: str | None = None, limit: int = LIMIT, chunk: int = CHUNK, overlap: int = OVERLAP) -> DataFrame:
    """Per row of docs: doc_id, n_bytes (UTF-8), n_tokens, over_limit (n_tokens > limit).

    A null or empty text has no bytes and no tokens. Repeated rows and ids stay as they are, an empty table
    gives no rows, other columns are ignored.
    """
    ship(docs.sparkSession)
    place = model_file or vocabulary(MODEL)

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = encoder(place, chunk, overlap)
        for batch in batches:
            n_bytes, n_tokens = [], []
            for value in batch.column(1):
                text = value.as_py()
                n_bytes.append(len(text.encode()))
                n_tokens.append(len(own.encode(text)))
            yield pa.RecordBatch.from_pydict({"doc_id": batch.column(0), "n_bytes": n_bytes, "n_tokens": n_tokens, "over_limit": [n > limit for n in n_tokens]})

    return texts(docs).mapInArrow(kernel, "doc_id long, n_bytes long, n_tokens long, over_limit boolean")


def op4_overlap_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return count_tokens(read(spark, sf_dir, "documents"))
