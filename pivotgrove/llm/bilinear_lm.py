"""Operator 2: a log-bilinear language model with noise-contrastive training, over counts of the whole corpus.

Every word has a class: the commonest words one each, the others one of a fixed number by their ending. The
model predicts the class from the classes before it: their vectors, weighted by position, add up to a
predicted vector, whose products with the class vectors are the scores. It is trained in numpy against noise
from the corpus's class frequencies, on every training document: in each pass every partition moves a copy of
the model over its own documents, and the copies' averages, weighted by tokens, are where the next pass begins.
The counts behind the noise, the biases and the words' shares of their classes cover every training document
too. A text's probability is normalised: batched matrix products give every class's score at every token, a word's share of its class is
its smoothed count, and each class keeps half a count for words that training lacks.

Counts of common words, up to a fixed number, go to every task as two arrays. Rarer words leave the scoring
pass as (row, word, times) and meet their counts in a join.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pivotgrove.llm.shingles import endings_at, hashes_at, mix, word_bounds
from pivotgrove.llm.tables import read
from pivotgrove.runtime import materialise, ship

WORD_CLASSES, ENDING_CLASSES = 128, 127
CONTEXT, WIDTH = 6, 16
COMMON_WORDS = 500_000  #: words whose counts every task holds, at most
EPOCHS, BATCH, NOISE, RATE, SEED = 3, 2048, 10, 0.15, 5
LANES, DRAWN = 16, 64  #: runs of tokens in a batch, and noise classes that it draws
MERGED = 256  #: copies of the model that one task adds up
END = np.uint64(0xE9D)  #: stands for the end of a text
_FLUSH, _RUN = 1 << 20, 1 << 18  #: distinct words of runs that a task holds, characters of a run


class Run:
    """Several texts as one array of bytes, so that few calls serve them all; a space between them keeps words apart.

    hashes: of the words of every text and its end; size: tokens of each text.
    """

    def __init__(self, texts: list[str]):
        whole = [t.encode() for t in texts]
        self.raw = np.frombuffer(b" ".join(whole), dtype=np.uint8)
        self.starts, self.ends = word_bounds(self.raw)
        borders = np.cumsum([len(t) + 1 for t in whole])
        self.size = np.diff(np.searchsorted(self.starts, borders), prepend=0) + 1
        self.first = np.cumsum(self.size) - self.size
        self.is_word = np.ones(int(self.size.sum()), dtype=bool)
        self.is_word[self.first + self.size - 1] = False
        self.hashes = np.full(len(self.is_word), END)
        self.hashes[self.is_word] = hashes_at(self.raw, self.starts, self.ends)

    def ending_classes(self, at: np.ndarray) -> np.ndarray:
        """Of the tokens at these places; the end's, 0, is not used, as it is a class of its own."""
        out = np.zeros(len(at), np.int32)
        words = np.flatnonzero(self.is_word[at])
        place = at[words] - np.searchsorted(self.first, at[words], side="right") + 1  # an end before it for each text before it
        out[words] = mix(endings_at(self.raw, self.starts[place], self.ends[place])) % np.uint64(ENDING_CLASSES)
        return out


def runs(texts: pa.Array, most: int) -> Iterator[tuple[int, Run]]:
    """(place of the first, run) of neighbouring texts that together have about so many characters; a longer text is a run alone."""
    held, waiting, begun = [], 0, 0
    for at, value in enumerate(texts):
        text = value.as_py()
        if held and waiting + len(text) > most:
            yield begun, Run(held)
            held, waiting, begun = [], 0, at
        held.append(text)
        waiting += len(text)
    if held:
        yield begun, Run(held)


def _count_kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    held, waiting = [], 0

    def counted() -> pa.RecordBatch:
        h, e, c = (np.concatenate(x) for x in zip(*held, strict=True))
        h, at, group = np.unique(h, return_index=True, return_inverse=True)
        return pa.RecordBatch.from_arrays([pa.array(h.view(np.int64)), pa.array(e[at]), pa.array(np.bincount(group, c).astype(np.int64))], ["word", "ending", "n"])

    for batch in batches:
        for _, run in runs(batch.column(1), _RUN):
            h, at, n = np.unique(run.hashes, return_index=True, return_counts=True)
            held.append((h, run.ending_classes(at), n))
            waiting += len(h)
            if waiting >= _FLUSH:
                yield counted()
                held, waiting = [], 0
    if held:
        yield counted()


@dataclass
class Classes:
    """word -> class: sorted hashes of the common words, their counts and classes; shares of every class."""

    words: np.ndarray
    counts: np.ndarray
    of: np.ndarray
    total: np.ndarray  # training tokens of each class
    distinct: np.ndarray  # training words of each class

    def look_up(self, h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(class, count), each -1 where the word is not common."""
        if not len(self.words):
            return np.full(len(h), -1), np.full(len(h), -1)
        at = np.minimum(np.searchsorted(self.words, h), len(self.words) - 1)
        hit = self.words[at] == h
        return np.where(hit, self.of[at], -1), np.where(hit, self.counts[at], -1)


N_CLASSES = WORD_CLASSES + ENDING_CLASSES


@dataclass
class LogBilinear:
    before: np.ndarray  # (classes + 1, width): vectors of classes before the token; the last stands for none
    weight: np.ndarray  # (context, width): by distance
    after: np.ndarray  # (classes, width)
    bias: np.ndarray

    @classmethod
    def start(cls, share: np.ndarray, seed: int = SEED) -> LogBilinear:
        draw = np.random.default_rng(seed)
        return cls(draw.normal(0, 0.1, (len(share) + 1, WIDTH)), np.ones((CONTEXT, WIDTH)) / CONTEXT, draw.normal(0, 0.1, (len(share), WIDTH)), np.log(share))

    def arrays(self) -> list[np.ndarray]:
        return [self.before, self.weight, self.after, self.bias]

    def fit(self, documents: list[np.ndarray], share: np.ndarray, square: list[np.ndarray], seed: int = SEED) -> LogBilinear:
        """One pass that tells each token from NOISE tokens drawn by share; Adagrad over batches, square its sums.

        A batch is LANES runs of tokens from distant places of the shuffled documents. Its tokens share DRAWN
        drawn classes, which together count as NOISE for each token.
        """
        draw = np.random.default_rng(seed)
        none = np.full(CONTEXT, len(share))  # stands before every document, and is no target
        stream = np.concatenate([x for i in draw.permutation(len(documents)) for x in (none, documents[i])])
        wide = -(-len(stream) // LANES)
        stream = np.concatenate((none, stream, np.full(wide * LANES - len(stream), len(share))))
        lanes = stream[(np.arange(LANES) * wide)[:, None] + np.arange(wide + CONTEXT)]
        cumulated, log_noise = np.cumsum(share), np.log(NOISE * share)
        at_width = np.arange(WIDTH)
        for lo in range(0, wide, BATCH // LANES):
            c = lanes[:, lo : lo + BATCH // LANES + CONTEXT]
            target = c[:, CONTEXT:]
            run, real = target.shape[1], target.ravel() < len(share)
            if not real.any():
                continue
            w, each = np.where(real, target.ravel(), 0), (real / real.sum()).astype(np.float32)
            k = np.minimum(np.searchsorted(cumulated, draw.random(DRAWN) * cumulated[-1]), len(share) - 1)
            seen, weight = self.before.astype(np.float32).take(c, 0), self.weight.astype(np.float32)
            back = [slice(CONTEXT - 1 - i, CONTEXT - 1 - i + run) for i in range(CONTEXT)]  # the tokens i + 1 before the targets
            guess = sum(seen[:, x] * v for x, v in zip(back, weight, strict=True)).reshape(-1, WIDTH)
            after, bias = self.after.astype(np.float32), (self.bias - log_noise).astype(np.float32)
            q = after.take(w, 0)
            own = ((1 / (1 + np.exp(-np.clip(np.einsum("bd,bd->b", guess, q) + bias.take(w), -30, 30))) - 1) * each).astype(np.float32)
            drawn = after.take(k, 0)
            gap = guess @ -drawn.T  # the share of each drawn class, in place: each * NOISE / DRAWN over 1 + exp(-z)
            gap -= bias.take(k)
            np.minimum(gap, 30, out=gap)  # what is far below adds nothing to 1
            np.exp(gap, out=gap)
            gap += 1
            np.divide((each * np.float32(NOISE / DRAWN))[:, None], gap, out=gap)
            q *= own[:, None]
            g_guess = gap @ drawn
            g_guess += q
            g_after = np.bincount((w[:, None] * WIDTH + at_width).ravel(), (own[:, None] * guess).ravel(), self.after.size).reshape(self.after.shape)
            np.add.at(g_after, k, (gap.T @ guess).astype(float))
            g_bias = np.bincount(w, own, len(share)) + np.bincount(k, gap.sum(0), len(share))
            g_guess = g_guess.reshape(LANES, run, WIDTH)
            g_seen = np.zeros(seen.shape, np.float32)
            for x, v in zip(back, weight, strict=True):
                g_seen[:, x] += g_guess * v
            g_before = np.bincount((c.reshape(-1, 1) * WIDTH + at_width).ravel(), g_seen.ravel(), self.before.size).reshape(self.before.shape)
            ones = np.ones(LANES * run, np.float32)
            g_weight = np.stack([ones @ (g_guess * seen[:, x]).reshape(-1, WIDTH) for x in back]).astype(float)
            for x, s, g in zip(self.arrays(), square, (g_before, g_weight, g_after, g_bias), strict=True):
                s += g * g
                x -= RATE * g / np.sqrt(s)
        return self

    def log_probabilities(self, context: np.ndarray, target: np.ndarray, block: int = 512) -> np.ndarray:
        """Natural log of each target class given its context, normalised over all classes."""
        out = np.empty(len(target))
        # One product for every distance and class: a context adds up rows of it. The last column adds the bias.
        moved = [np.column_stack((self.before * w, np.full(len(self.before), i == 0))).astype(np.float32) for i, w in enumerate(self.weight)]
        after = np.vstack((self.after.T, self.bias)).astype(np.float32)
        every = np.ones(len(self.bias), np.float32)
        row = np.arange(block)
        for lo in range(0, len(target), block):
            c = context[lo : lo + block]
            guess = moved[0].take(c[:, 0], 0)
            for i in range(1, CONTEXT):
                guess += moved[i].take(c[:, i], 0)
            z = guess @ after
            own = z[row[: len(c)], target[lo : lo + block]].astype(float)
            top = float(z.max())
            if abs(top) < 60:  # neither the exponentials nor their sums leave the range
                top = 0.0
            else:
                z -= np.float32(top)
            total = np.exp(z, out=z) @ every
            out[lo : lo + block] = own - top - np.log(np.maximum(total, 1e-300))
            for i in np.flatnonzero(total < 1e-20):  # a row far below the block's top is added up by itself
                alone = guess[i, :WIDTH].astype(float) @ self.after.T + self.bias
                out[lo + i] = alone[target[lo + i]] - alone.max() - np.log(np.exp(alone - alone.max()).sum())
        return out


def contexts(classes: np.ndarray, starts: np.ndarray) -> np.ndarray:
    """(tokens, CONTEXT): the classes before each token within its document, nearest first."""
    at = np.arange(len(classes))
    first = np.repeat(starts, np.diff(np.append(starts, len(classes))))
    out = np.full((len(classes), CONTEXT), N_CLASSES, dtype=np.int64)
    for i in range(CONTEXT):
        fits = at - i - 1 >= first
        out[fits, i] = classes[at[fits] - i - 1]
    return out


def _class_kernel(shared, base_total: float):
    """What one reading of a text gives: the classes of its tokens, sums over its words' counts, and its rarer words."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        classes = shared.value
        share = np.log10(classes.total + 0.5 * (classes.distinct + 1))
        part, row = TaskContext.get().partitionId(), 0
        for batch in batches:
            for begun, run in runs(batch.column(1), _RUN):
                h, n, starts = run.hashes, run.size, run.first
                of, count = classes.look_up(h)
                rarer = np.flatnonzero(count < 0)
                of[rarer] = WORD_CLASSES + run.ending_classes(rarer)
                own = np.log10(np.maximum(count, 0) + 0.5)
                own[rarer] = 0.0
                base = np.add.reduceat(own, starts) - n * base_total
                inside = np.add.reduceat(own - share[of], starts)
                known = np.add.reduceat((count > 0).astype(np.int64), starts)
                # Each text's rarer words with the times that they occur in it.
                text, word = np.searchsorted(starts, rarer, side="right") - 1, h[rarer]
                order = np.lexsort((word, text))
                text, word = text[order], word[order]
                new = np.flatnonzero(np.append(True, (text[1:] != text[:-1]) | (word[1:] != word[:-1]))[: len(word)])
                times = np.diff(np.append(new, len(word)))
                rare = pa.StructArray.from_arrays([pa.array(word[new].view(np.int64)), pa.array(times)], ["word", "times"])
                held = np.searchsorted(text[new], np.arange(len(n) + 1)).astype(np.int32)
                ends = np.append(0, np.cumsum(2 * n)).astype(np.int32)
                written = pa.Array.from_buffers(pa.binary(), len(n), [None, pa.py_buffer(ends), pa.py_buffer(of.astype("<i2"))])
                rows = np.arange(row, row + len(n)) + (part << 40)
                row += len(n)
                whole = batch.slice(begun, len(n))
                yield pa.RecordBatch.from_arrays([pa.array(rows), whole.column(0), whole.column(2), pa.array(n), pa.array(known), pa.array(base), pa.array(inside), pa.ListArray.from_arrays(pa.array(held), rare), written], ["row", "doc_id", "held_out", "n_tokens", "known", "base", "inside", "rare", "classes"])

    return kernel


def _joined(lists: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """(classes of all, where each begins)."""
    n = np.array([len(x) // 2 for x in lists])
    return np.frombuffer(b"".join(lists), "<i2").astype(np.int64), np.concatenate(([0], np.cumsum(n)[:-1]))


def _fit_kernel(shared, share: np.ndarray, turn: int):
    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model, square = shared.value
        model, square = LogBilinear(*[x.copy() for x in model.arrays()]), [x.copy() for x in square]
        part, tokens, held, waiting = TaskContext.get().partitionId(), 0, [], 0

        def learn() -> None:
            model.fit([np.frombuffer(x, "<i2").astype(np.int64) for x in held], share, square, hash((SEED, turn, part, tokens)) & 0x7FFFFFFF)

        for batch in batches:
            for value in batch.column(0):
                held.append(value.as_py())
                waiting += len(held[-1]) // 2
                if waiting >= 500_000:
                    learn()
                    tokens, held, waiting = tokens + waiting, [], 0
        if held:
            learn()
            tokens += waiting
        if tokens:
            both = np.concatenate([x.ravel() for x in (*model.arrays(), *square)])
            yield pa.RecordBatch.from_arrays([pa.array([part]), pa.array([tokens]), pa.array([(tokens * both).tobytes()], pa.binary())], ["part", "tokens", "model"])

    return kernel


def _merge_kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Copies of the model, already times their tokens, added up in the order they come."""
    first, tokens, total = 0, 0, None
    for batch in batches:
        for part, n, model in zip(*(x.to_pylist() for x in batch.columns), strict=True):
            value = np.frombuffer(model)
            first, total = (part, value.copy()) if total is None else (first, total + value)
            tokens += n
    if total is not None:
        yield pa.RecordBatch.from_arrays([pa.array([first]), pa.array([tokens]), pa.array([total.tobytes()], pa.binary())], ["part", "tokens", "model"])


def train(encoded: DataFrame, share: np.ndarray, epochs: int = EPOCHS) -> tuple[LogBilinear, int]:
    """The model after so many passes over every training row of encoded, and the tokens of each pass."""
    spark = encoded.sparkSession
    model, tokens = LogBilinear.start(share), 0
    square = [np.full(x.shape, 1e-3) for x in model.arrays()]
    training = encoded.where(~F.col("held_out")).select("classes")
    kind = "part long, tokens long, model binary"
    groups = max(1, training.rdd.getNumPartitions() // MERGED)
    for turn in range(epochs):
        copies = training.mapInArrow(_fit_kernel(spark.sparkContext.broadcast((model, square)), share, turn), kind)
        dealt = copies.repartition(groups, F.floor(F.col("part") / MERGED)).sortWithinPartitions("part")
        got = dealt.mapInArrow(_merge_kernel, kind).toArrow().sort_by("part")
        tokens = sum(got["tokens"].to_pylist())
        if not tokens:
            break
        both = sum(np.frombuffer(x) for x in got["model"].to_pylist()) / tokens
        shapes = [x.shape for x in model.arrays()]
        cuts = np.cumsum([int(np.prod(x)) for x in shapes * 2])[:-1]
        new = [x.reshape(shape) for x, shape in zip(np.split(both, cuts), shapes * 2, strict=True)]
        model, square = LogBilinear(*new[:4]), new[4:]
    return model, tokens


def _score_kernel(shared):
    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            at, lists, score = 0, batch.column(1).to_pylist(), []
            while at < len(lists):
                begun, tokens = at, 0
                while at < len(lists) and (tokens < 200_000 or at == begun):
                    tokens += len(lists[at]) // 2
                    at += 1
                of, starts = _joined(lists[begun:at])
                score.append(np.add.reduceat(shared.value.log_probabilities(contexts(of, starts), of) / np.log(10), starts))
            keep = [batch.column(i) for i in (0, *range(2, batch.num_columns))]
            names = [batch.schema.names[i] for i in (0, *range(2, batch.num_columns))]
            yield pa.RecordBatch.from_arrays([*keep, pa.array(np.concatenate(score) if score else np.empty(0))], [*names, "by_class"])

    return kernel


def count_words(training: DataFrame) -> DataFrame:
    """(word, ending, c) of every token in the training documents, each partition's counts added up first."""
    return materialise(training.mapInArrow(_count_kernel, "word long, ending int, n long").groupBy("word").agg(F.min("ending").alias("ending"), F.sum("n").alias("c")), "lm-counts")


def fit_classes(counts: DataFrame, common_words: int = COMMON_WORDS) -> tuple[Classes, int]:
    """The classes, and the least count that a common word has."""
    spread = counts.groupBy("c").agg(F.count("*").alias("words")).orderBy(F.desc("c"))
    least, room = None, common_words
    for row in spread.toLocalIterator():  # distinct counts, from the largest until the room is used
        if row.words > room:
            break
        least, room = row.c, room - row.words
    end = int(END)
    least = (1 << 62) if least is None else least
    got = counts.where((F.col("c") >= least) | (F.col("word") == end)).toArrow()
    words, c, endings = got["word"].to_numpy().view(np.uint64), got["c"].to_numpy(), got["ending"].to_numpy()
    order = np.argsort(words)
    words, c, endings = words[order], c[order], endings[order]
    of = WORD_CLASSES + endings.astype(np.int64)
    ranked = np.lexsort((words, -c))
    ranked = np.concatenate((ranked[words[ranked] == END], ranked[words[ranked] != END]))[:WORD_CLASSES]  # the end is class 0
    of[ranked] = np.arange(len(ranked))
    total, distinct = np.zeros(N_CLASSES), np.zeros(N_CLASSES)
    for row in counts.groupBy("ending").agg(F.sum("c").alias("c"), F.count("*").alias("n")).collect():  # a row for each ending class
        total[WORD_CLASSES + row.ending] += row.c
        distinct[WORD_CLASSES + row.ending] += row.n
    for i, w in enumerate(ranked):
        total[WORD_CLASSES + endings[w]] -= c[w]
        distinct[WORD_CLASSES + endings[w]] -= 1
        total[i], distinct[i] = c[w], 1
    return Classes(words, c, of, total, distinct), least


def score_texts(docs: DataFrame, common_words: int = COMMON_WORDS) -> DataFrame:
    """Per row of docs: doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score.

    Learns from all rows whose crc32(doc_id as text) mod 5 is not 1 (a null doc_id is such a row). A null or
    empty text is its end alone. Repeated rows are counted and scored each, an empty table gives no rows, other
    columns are ignored; without a training row every count is 0 and the model is flat. The class vectors, and
    so score, depend a little on how the rows lie in partitions.
    """
    spark = docs.sparkSession
    ship(spark)
    held_out = F.coalesce(F.crc32(F.col("doc_id").cast("string")) % 5 == 1, F.lit(False))
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text")).withColumn("held_out", held_out)
    counts = count_words(rows.where(~F.col("held_out")))
    train_tokens, distinct = counts.agg(F.coalesce(F.sum("c"), F.lit(0)), F.count("*")).first()
    classes, least = fit_classes(counts, common_words)
    share = (classes.total + 0.5 * (classes.distinct + 1)) / (classes.total + 0.5 * (classes.distinct + 1)).sum()
    base_total = float(np.log10(train_tokens + 0.5 * (distinct + 1)))
    kind = "row long, doc_id long, held_out boolean, n_tokens long, known long, base double, inside double, rare array<struct<word:long,times:long>>"
    encoded = materialise(rows.mapInArrow(_class_kernel(spark.sparkContext.broadcast(classes), base_total), f"{kind}, classes binary"), "lm-classes")
    model, _ = train(encoded, share)
    by_class = encoded.select("row", "classes", "doc_id", "held_out", "n_tokens", "known", "base", "inside").mapInArrow(_score_kernel(spark.sparkContext.broadcast(model)), kind[: kind.index(", rare")] + ", by_class double")
    scored = by_class.withColumn("score", F.col("inside") + F.col("by_class"))
    rare = encoded.select("row", F.explode("rare").alias("r")).select("row", "r.word", "r.times").join(counts.where(F.col("c") < least).select("word", "c"), "word", "left")
    c = F.coalesce("c", F.lit(0))
    late = rare.groupBy("row").agg(F.sum(F.col("times") * F.log10(c + 0.5)).alias("more"), F.sum(F.when(c > 0, F.col("times")).otherwise(0)).alias("seen"))
    more, seen = F.coalesce("more", F.lit(0.0)), F.coalesce("seen", F.lit(0))
    out = scored.join(late, "row", "left")
    return out.select("doc_id", "held_out", "n_tokens", (F.col("known") + seen).alias("n_known"), F.lit(train_tokens).cast("long").alias("train_tokens"), (F.col("base") + more).alias("base_score"), (F.col("score") + more).alias("score"))


def op2_log_bilinear_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    return score_texts(read(spark, sf_dir, "documents"))
