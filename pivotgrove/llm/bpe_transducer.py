"""Operator 9: byte-level BPE by a lazily determinised transducer, and streaming decode.

The merges of a rank file define which two tokens may stand side by side: u, t may when the merges, run on
the bytes of u and t together, leave exactly u and t. A token sequence whose neighbours all may stand side
by side is the one that the merges give. That turns the merges into a transducer: after each byte it holds
the partial tokens that may still grow (a node of the vocabulary's trie) with the tokens pending before
each; what all of them agree on is emitted, so the lookahead is at most the longest token. States and arcs
are made when first met and kept up to a bound. A memo of whole pretokens, bounded too, stands before it.
"""

from __future__ import annotations

import base64
import functools
import hashlib
import struct
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from pivotgrove.llm.tables import read, texts, vocabulary
from pivotgrove.runtime import ship

RANKS = "byte_bpe_multi_50k.tiktoken"
MEMO_ENTRIES = 300_000
ARC_ENTRIES = 400_000
FEW = 24


_NEVER = 1 << 60


def merge_by_rank(piece: bytes, ranks: dict[bytes, int], stop: int = _NEVER) -> list[int]:
    """The plain definition: merge the adjacent pair of lowest rank below stop, leftmost first, until none is left."""
    parts = [piece[i : i + 1] for i in range(len(piece))]
    while len(parts) > 1:
        best = min(range(len(parts) - 1), key=lambda i: (ranks.get(parts[i] + parts[i + 1], _NEVER), i))
        if ranks.get(parts[best] + parts[best + 1], _NEVER) >= stop:
            break
        parts[best : best + 2] = [parts[best] + parts[best + 1]]
    return [ranks[p] for p in parts]


class Transducer:
    """step(state, byte) walks the lazily made automaton; encode(piece) walks it and emits."""

    def __init__(self, ranks: dict[bytes, int], max_arcs: int = ARC_ENTRIES):
        self.ranks = ranks
        self.surface = {i: b for b, i in ranks.items()}
        self.max_arcs = max_arcs
        self.trie: list[dict[int, int]] = [{}]
        self.token_at: dict[int, int] = {}
        for surface, token in ranks.items():
            node = 0
            for byte in surface:
                nxt = self.trie[node].get(byte)
                if nxt is None:
                    nxt = self.trie[node][byte] = len(self.trie)
                    self.trie.append({})
                node = nxt
            self.token_at[node] = token
        self.width = {token: len(surface) for surface, token in ranks.items()}
        self.hope: dict[int, bool] = {}
        self.few: list[tuple[int, ...] | None] = [()] * len(self.trie)
        for node in range(len(self.trie) - 1, -1, -1):  # children come after their parents
            below: list[int] = []
            for child in self.trie[node].values():
                if below is not None:
                    more = self.few[child]
                    below = None if more is None or len(below) + len(more) > FEW else [*below, *more, *([self.token_at[child]] if child in self.token_at else [])]
            self.few[node] = None if below is None else tuple(below)
        self.may: dict[tuple[int, int], bool] = {}
        self.split: dict[int, tuple[int, int] | None] = {}
        self.spines: dict[tuple[int, int], tuple[int, ...]] = {}
        self._reset()

    def _reset(self) -> None:
        self.states: list[tuple[tuple[int, int], ...]] = [((0, -1),)]  # (trie node, token before it or -1), ...; the root's is last
        self.number = {self.states[0]: 0}
        self.arcs: dict[int, tuple[int, int, int]] = {}
        self.may.clear()
        self.hope.clear()

    def viable(self, node: int, before: int) -> bool:
        """Whether a longer token below this node could follow; taken as yes where there are many."""
        below = self.few[node]
        if below is None or before < 0:
            return True
        key = node << 17 | before
        known = self.hope.get(key)
        if known is None:
            known = self.hope[key] = any(self.adjacent(before, t) for t in below)
        return known

    def halves(self, token: int) -> tuple[int, int] | None:
        """The two tokens whose merge makes this one; None for a single byte."""
        if token not in self.split:
            raw = self.surface[token]
            parts = merge_by_rank(raw, self.ranks, stop=token)
            self.split[token] = tuple(parts) if len(parts) == 2 else None
            if len(raw) > 1 and len(parts) != 2:
                raise ValueError(f"token {token} is not the merge of two")
        return self.split[token]

    def spine(self, token: int, side: int) -> tuple[int, ...]:
        """The tokens at the left (0) or right (1) edge of this one while it is merged, from its byte to itself."""
        key = (token, side)
        if key not in self.spines:
            parts = self.halves(token)
            self.spines[key] = (token,) if parts is None else self.spine(parts[side], side) + (token,)
        return self.spines[key]

    def adjacent(self, u: int, t: int) -> bool:
        """Whether no merge joins the two while each is being made: an edge token lives until its parent's rank comes."""
        if u < 0:
            return True
        key = (u, t)
        known = self.may.get(key)
        if known is None:
            left, right, i, j, known = self.spine(u, 1), self.spine(t, 0), 0, 0, True
            while known:
                ends_left = left[i + 1] if i + 1 < len(left) else _NEVER
                ends_right = right[j + 1] if j + 1 < len(right) else _NEVER
                joined = self.ranks.get(self.surface[left[i]] + self.surface[right[j]], _NEVER)
                if joined < ends_left and joined <= ends_right and joined < _NEVER:
                    known = False
                elif ends_left == ends_right == _NEVER:
                    break
                elif ends_left <= ends_right:
                    i += 1
                else:
                    j += 1
            self.may[key] = known
        return known

    def step(self, state: int, byte: int) -> tuple[int, int, int]:
        """(next state, token that ends here on the only legal path, bytes after which nothing before can change)."""
        arc = self.arcs.get(state << 8 | byte)
        if arc is None:
            arc = self.arcs[state << 8 | byte] = self._arc(state, byte)
        return arc

    def _arc(self, state: int, byte: int) -> tuple[int, int, int]:
        held, ended = [], -1
        for node, before in self.states[state]:
            nxt = self.trie[node].get(byte)
            if nxt is not None:
                if ended < 0:
                    token = self.token_at.get(nxt)
                    if token is not None and self.adjacent(before, token):
                        ended = token
                if self.trie[nxt] and self.viable(nxt, before):
                    held.append((nxt, before))
        if ended < 0:
            raise ValueError("the vocabulary lacks a byte or is not a merge vocabulary")
        held.append((0, ended))
        new = tuple(held)
        number = self.number.get(new)
        if number is None:
            number = self.number[new] = len(self.states)
            self.states.append(new)
        return number, ended, len(held)

    def encode(self, piece: bytes) -> list[int]:
        """Where one partial token alone is left, all tokens before it are emitted: the lookahead ends there."""
        if len(self.arcs) > self.max_arcs:
            self._reset()
        state, ends, done, out, arcs = 0, [], 0, [], self.arcs
        for at, byte in enumerate(piece):
            arc = arcs.get(state << 8 | byte) or self.step(state, byte)
            state, token, alive = arc
            ends.append(token)
            if alive == 1 and at - done > 64:
                out += self._back(ends, done)
                done = at + 1
        return out + self._back(ends, done)

    def _back(self, ends: list[int], done: int) -> list[int]:
        at, found = len(ends), []
        while at > done:
            token = ends[at - 1]
            found.append(token)
            at -= self.width[token]
        return found[::-1]


#: Fixed values of UTF-8: the lead byte ranges, the number of bytes that follow, and the range of the first of them.
_LEADS = (
    (0xC2, 0xDF, 1, 0x80, 0xBF), (0xE0, 0xE0, 2, 0xA0, 0xBF), (0xE1, 0xEC, 2, 0x80, 0xBF), (0xED, 0xED, 2, 0x80, 0x9F),
    (0xEE, 0xEF, 2, 0x80, 0xBF), (0xF0, 0xF0, 3, 0x90, 0xBF), (0xF1, 0xF3, 3, 0x80, 0xBF), (0xF4, 0xF4, 3, 0x80, 0x8F),
)


@functools.lru_cache(maxsize=None)
def utf8_step(state: tuple[int, int, int], byte: int) -> tuple[int, int, int] | None:
    """state: (bytes still due, least and greatest next byte), (0, 0, 0) between characters; None: not UTF-8."""
    due, low, high = state
    if due:
        return None if not low <= byte <= high else ((due - 1, 0x80, 0xBF) if due > 1 else (0, 0, 0))
    if byte < 0x80:
        return (0, 0, 0)
    for first, final, follow, lo, hi in _LEADS:
        if first <= byte <= final:
            return (follow, lo, hi)
    return None


class StreamingDecoder:
    """feed(ids) gives the bytes of whole characters; an unfinished character waits for the next ids.

    Bytes that are not UTF-8 pass unchanged (decoding ids must give back any bytes); `broken` counts them.
    """

    def __init__(self, surface: list[bytes]):
        self.surface = surface
        self.state = (0, 0, 0)
        self.held = b""
        self.broken = 0
        self._whole: dict[tuple, tuple | None] = {}
        self.partial = np.array([self._token((0, 0, 0), i) != (0, 0, 0) for i in range(len(surface))])

    def _token(self, state: tuple, token: int) -> tuple | None:
        key = (state, token)
        if key not in self._whole:
            for byte in self.surface[token]:
                state = utf8_step(state, byte)
                if state is None:
                    break
            self._whole[key] = state
        return self._whole[key]

    def feed(self, ids: Iterable[int]) -> bytes:
        """Tokens of whole characters are joined in runs; the machine steps through the others only."""
        ids = np.asarray(ids, dtype=np.int64)
        out, surface, state, at = [self.held], self.surface, self.state, 0
        listed = ids.tolist()
        for odd in [*np.flatnonzero(self.partial[ids]).tolist(), len(listed)]:
            while at < odd and state[0]:  # a character is due, but this token starts a new one
                state = self._advance(state, listed[at], out)
                at += 1
            if at < odd:
                out.extend(map(surface.__getitem__, listed[at:odd]))
                at = odd
            if at == odd < len(listed):
                state = self._advance(state, listed[at], out)
                at += 1
        self.state, joined = state, b"".join(out)
        tail = 0
        if state[0]:
            tail = 1
            while joined[-tail] & 0xC0 == 0x80:
                tail += 1
        self.held = joined[len(joined) - tail :]
        return joined[: len(joined) - tail]

    def _advance(self, state: tuple, token: int, out: list[bytes]) -> tuple:
        out.append(self.surface[token])
        nxt = self._token(state, token)
        if nxt is None:
            self.broken += 1
            return (0, 0, 0)
        return nxt

    def end(self) -> bytes:
        rest, self.held, self.state = self.held, b"", (0, 0, 0)
        self.broken += bool(rest)
        return rest


class _Memo(dict):
    def __init__(self, codec: Codec):
        self.codec = codec

    def __missing__(self, piece: str) -> bytes:
        raw = piece.encode()
        whole = self.codec.ranks.get(raw)
        ids = [whole] if whole is not None else self.codec.machine.encode(raw)
        out = struct.pack(f"<{len(ids)}I", *ids)
        if len(piece) <= 64:  # a long run is not worth its memory
            self[piece] = out
        return out


class Codec:
    def __init__(self, rank_file: str, memo_entries: int = MEMO_ENTRIES):
        import public_tokenizers
        import regex

        with open(rank_file, "rb") as lines:
            self.ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, lines)}
        self.machine = Transducer(self.ranks)
        self.split = regex.compile(public_tokenizers.PATTERN).findall
        self.surface = [b""] * (max(self.ranks.values()) + 1)
        for raw, token in self.ranks.items():
            self.surface[token] = raw
        self.memo_entries = memo_entries
        self.memo = _Memo(self)
        self.decoder = StreamingDecoder(self.surface)

    def encode_packed(self, text: str) -> bytes:
        """Little-endian unsigned 32-bit ids."""
        if len(self.memo) > self.memo_entries:
            self.memo.clear()
        return b"".join(map(self.memo.__getitem__, self.split(text)))

    def encode(self, text: str) -> list[int]:
        return np.frombuffer(self.encode_packed(text), "<u4").tolist()

    def decode(self, ids: Iterable[int], block: int = 65_536) -> bytes:
        ids, decoder, out = list(ids), self.decoder, []
        if len(decoder._whole) > self.memo_entries:
            decoder._whole.clear()
        for i in range(0, len(ids), block):
            out.append(decoder.feed(ids[i : i + block]))
        out.append(decoder.end())
        return b"".join(out)


@functools.lru_cache(maxsize=2)
def codec(rank_file: str) -> Codec:
    return Codec(rank_file)


def encode_decode(docs: DataFrame, rank_file: str | None = None, keep_ids: bool = False) -> DataFrame:
    """Per row of docs: doc_id, n_tokens, ids_sha256, decoded_sha256, and with keep_ids the packed ids.

    A null or empty text has no token and the hash of no bytes. Repeated rows and ids stay as they are, an
    empty table gives no rows, other columns are ignored. Texts are split whole, whatever their length.
    """
    ship(docs.sparkSession)
    place = rank_file or vocabulary(RANKS)

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = codec(place)
        for batch in batches:
            rows = {"doc_id": batch.column(0), "n_tokens": [], "ids_sha256": [], "decoded_sha256": []} | ({"ids": []} if keep_ids else {})
            for text in batch.column(1):
                packed = own.encode_packed(text.as_py())
                rows["n_tokens"].append(len(packed) // 4)
                rows["ids_sha256"].append(hashlib.sha256(packed).hexdigest())
                rows["decoded_sha256"].append(hashlib.sha256(own.decode(np.frombuffer(packed, "<u4").tolist())).hexdigest())
                if keep_ids:
                    rows["ids"].append(packed)
            yield pa.RecordBatch.from_pydict(rows)

    return texts(docs).mapInArrow(kernel, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string" + ", ids binary" * keep_ids)


def op9_bpe_transducer(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encode_decode(read(spark, sf_dir, "documents"))
