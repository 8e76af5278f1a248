"""Operator 1: personal data, by fixed shapes and by patterns that the corpus itself teaches.

Seeds are what the fixed shapes find. Their patterns are the words beside them, signs and digits skipped, and
the way they are written (digits and letters by class). Windows of the text that could be an identifier at all
(spelled-out addresses, runs of digits and signs, colon groups, numbers that pass a card's check) are instances
without a label; a pattern extracts the instances that stand in it. On the graph of patterns and instances
a pattern is trusted by the share of its instances that are trusted, an instance by its patterns, round after
round, seeds staying trusted: instances that patterns promote make new patterns trusted, which extract more.
A window is added to the spans where its own patterns, or its instance in the whole corpus, reach the threshold.
"""

from __future__ import annotations

import hashlib
import ipaddress
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pivotgrove.llm.tables import read, texts
from pivotgrove.runtime import discard, materialise, ship

KINDS = ("email", "ip", "card", "phone")
#: The shapes of the base spans.
EMAIL_DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
IP = re.compile(r"[0-9]+(?:\.[0-9]+)(?:\.[0-9]+)(?:\.[0-9]+)")
CARD = re.compile(r"[0-9](?:[ -]?[0-9])+")
PHONE = re.compile(r"\+[0-9][ ().0-9-]+[0-9]")
#: Windows that could be an identifier.
SPELLED = re.compile(r"[A-Za-z0-9._%+-]{2,64}(?: ?[\[(]at[\])] ?[A-Za-z0-9-]{2,63}(?: ?[\[(]dot[\])] ?| dot |\.)| at [A-Za-z0-9-]{2,63}(?: ?[\[(]dot[\])] ?| dot ))[A-Za-z0-9-]{2,63}(?:(?: ?[\[(]dot[\])] ?| dot |\.)[A-Za-z0-9-]{2,63}){0,3}")
COLONS = re.compile(r"(?<![\w:.])[0-9A-Fa-f:]{4,39}(?![\w:])")
NUMBER = re.compile(r"(?<![\w.])[+(]{0,2}[0-9][0-9 ().\-/]{5,24}(?![0-9])(?<=[0-9])(?![A-Za-z_])")
_DIGIT, _LETTERS = re.compile("[0-9]"), re.compile(r"[^\W\d_]+")
_WORD_BEFORE, _WORD_AFTER = re.compile(r"([^\W\d_]+)[\W\d_]*\Z"), re.compile(r"[\W\d_]*([^\W\d_]+)")
_NEAR = 48

ROUNDS, THRESHOLD, SUPPORT = 4, 0.6, 5


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        n = int(c) * (1 + i % 2)
        total += n - 9 * (n > 9)
    return total % 10 == 0


def _digits(value: str) -> str:
    return "".join(c for c in value if c.isdigit())


def base_spans(text: str) -> dict[str, list[tuple[int, int]]]:
    """Leftmost non-overlapping matches of each kind; what fails its check is dropped, nothing is tried again."""
    found: dict[str, list[tuple[int, int]]] = {k: [] for k in KINDS}
    at, free = text.find("@"), 0
    while at >= 0:  # what stands before the sign is looked up backwards, so that texts without it cost nothing
        start = at
        while start > free and (c := text[start - 1]) < "\x7f" and (c.isalnum() or c in "._%+-"):
            start -= 1
        domain = EMAIL_DOMAIN.match(text, at + 1) if start < at else None
        if domain:
            found["email"].append((start, domain.end()))
            free = domain.end()
        at = text.find("@", max(at + 1, free))
    for m in IP.finditer(text):
        if all(len(p.lstrip("0")) <= 3 and int(p[-3:]) <= 255 for p in m[0].split(".")):
            found["ip"].append(m.span())
    for m in CARD.finditer(text):
        if m.end() - m.start() >= 16 and 16 <= len(d := _digits(m[0])) <= 19 and luhn(d):
            found["card"].append(m.span())
    if "+" in text:
        for m in PHONE.finditer(text):
            if 8 <= len(_digits(m[0])) <= 15:
                found["phone"].append(m.span())
    return found


def windows(text: str, taken: list[tuple[int, int]]) -> list[tuple[str, int, int]]:
    """What could be an identifier of a kind outside the base spans; one window may stand for two kinds."""
    out, spelled = [], any(x in text for x in ("[at]", "(at)", " dot ", "[dot]", "(dot)"))
    free, at = [], 0
    for a, b in sorted(taken):
        free.append((at, a))
        at = max(at, b)
    for a, b in [*free, (at, len(text))]:
        if b - a < 6:
            continue
        part = text[a:b]
        if spelled:
            out += [("email", a + m.start(), a + m.end()) for m in SPELLED.finditer(part)]
        if part.count(":") > 1:
            for m in COLONS.finditer(part):
                if m[0].count(":") > 1 and _is_address(m[0]):
                    out.append(("ip", a + m.start(), a + m.end()))
        for m in NUMBER.finditer(part):
            digits = _digits(m[0])
            if 12 <= len(digits) <= 15 and luhn(digits):
                out.append(("card", a + m.start(), a + m.end()))
            if 7 <= len(digits) <= 15:
                out.append(("phone", a + m.start(), a + m.end()))
    return out


def _is_address(value: str) -> bool:
    try:
        return ipaddress.IPv6Address(value) is not None
    except ValueError:
        return False


def patterns_of(text: str, start: int, end: int) -> list[str]:
    """The word before, the two words before and the word after a span, lower-cased, and how the span is written."""
    out, before = [], text[max(0, start - _NEAR) : start]
    if m := _WORD_BEFORE.search(before):
        out.append("<" + m[1].lower())
        if m2 := _WORD_BEFORE.search(before[: m.start(1)]):
            out.append("<<" + m2[1].lower() + " " + m[1].lower())
    if m := _WORD_AFTER.match(text[end : end + _NEAR]):
        out.append(">" + m[1].lower())
    out.append("=" + _LETTERS.sub("a", _DIGIT.sub("9", text[start:end]))[:_NEAR])
    return out


def _written(spans: dict[str, list[tuple[int, int]]]) -> str:
    return ",".join(f"{k}:{a}:{b}" for k in KINDS for a, b in spans[k])


def _scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    hits = pa.list_(pa.struct([("kind", pa.int32()), ("start", pa.int64()), ("end", pa.int64()), ("seed", pa.bool_()), ("instance", pa.int64()), ("patterns", pa.list_(pa.string()))]))
    for batch in batches:
        rows: dict[str, list] = {"row_key": [], "base": [], "hits": []}
        for value in batch.column(1):
            text = value.as_py()
            spans = base_spans(text)
            all_base = [x for k in KINDS for x in spans[k]]
            listed = [(k, a, b, True) for k in KINDS for a, b in spans[k]] + [(*x, False) for x in windows(text, all_base)]
            rows["base"].append(_written(spans))
            rows["row_key"].append(int.from_bytes(hashlib.blake2b(text.encode(), digest_size=8).digest(), "little", signed=True) if listed else 0)
            rows["hits"].append([{"kind": KINDS.index(k), "start": a, "end": b, "seed": s, "instance": int.from_bytes(hashlib.blake2b(text[a:b].lower().encode(), digest_size=8).digest(), "little", signed=True), "patterns": patterns_of(text, a, b)} for k, a, b, s in listed])
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(rows["row_key"], pa.int64()), pa.array(rows["base"], pa.string()), pa.array(rows["hits"], hits)], ["doc_id", "row_key", "base", "hits"])


def score_graph(edges: DataFrame, rounds: int = ROUNDS, threshold: float = THRESHOLD, support: int = SUPPORT) -> tuple[DataFrame, DataFrame]:
    """((kind, pattern, trust), (kind, instance, trust)) from edges (kind, pattern, instance, seed), one row an edge.

    Trust of a pattern for a kind: the trust of its instances of that kind over the number of its instances of
    every kind and one more, so that a word beside all sorts of things teaches nothing; 0 under `support`
    instances. Trust of an instance that is no seed: one minus the product of its patterns' doubts,
    each pattern at most as strong as its trust; under the threshold it is not promoted and counts as none. Every sum
    is taken over pre-aggregated partial sums. The instances returned are the promoted ones, without seeds.
    """
    open_edges = edges.where(~F.col("seed"))
    trust = edges.select("kind", "pattern", "instance", F.when(F.col("seed"), 1.0).otherwise(0.0).alias("trust"))
    patterns = instances = None
    for turn in range(rounds):
        by_kind = trust.groupBy("kind", "pattern").agg(F.sum("trust").alias("s"), F.count("*").alias("n"))
        total = by_kind.groupBy("pattern").agg(F.sum("n").alias("n_all"))
        strength = F.when(F.col("n") >= support, F.col("s") / (F.col("n_all") + 1)).otherwise(0.0)
        older, patterns = patterns, materialise(by_kind.join(total, "pattern").select("kind", "pattern", strength.alias("trust")).where("trust > 0"), "pattern-trust")
        held = open_edges.join(patterns, ["kind", "pattern"])
        doubt = held.groupBy("kind", "instance").agg(F.sum(F.log1p(-F.least("trust", F.lit(0.999)))).alias("doubt"))
        previous, instances = instances, materialise(doubt.select("kind", "instance", (1 - F.exp("doubt")).alias("trust")).where(F.col("trust") >= threshold), "instance-trust")
        if turn:
            discard(older, previous)
        if instances.isEmpty():
            break  # seeds alone: the next round would say the same
        fresh = open_edges.join(instances, ["kind", "instance"], "left").select("kind", "pattern", "instance", F.coalesce("trust", F.lit(0.0)).alias("trust"))
        trust = edges.where("seed").select("kind", "pattern", "instance", F.lit(1.0).alias("trust")).union(fresh)
    return patterns, instances


def find_private(docs: DataFrame, rounds: int = ROUNDS, threshold: float = THRESHOLD, support: int = SUPPORT) -> DataFrame:
    """Per row of docs: doc_id, n_email, n_ip, n_card, n_phone (base spans), base_sha256, spans, n_added.

    A null or empty text has no span (and the hash of no bytes). Repeated rows get equal results, rows that share
    a doc_id or have none their own text's, an empty table gives no rows, other columns are ignored, texts of any
    length are read whole. A window that two kinds claim goes to the more trusted, at a tie to the first in KINDS.
    """
    ship(docs.sparkSession)
    scanned = materialise(texts(docs).mapInArrow(_scan, "doc_id long, row_key long, base string, hits array<struct<kind:int,start:long,end:long,seed:boolean,instance:long,patterns:array<string>>>"), "private-scan")
    hits = scanned.where(F.size("hits") > 0).select("doc_id", "row_key", F.explode("hits").alias("h")).select("doc_id", "row_key", "h.*")
    edges = materialise(hits.select("kind", "instance", "seed", F.explode("patterns").alias("pattern")).distinct(), "private-edges")
    patterns, instances = score_graph(edges, rounds, threshold, support)
    place = ["doc_id", "row_key", "kind", "start", "end"]
    loose = hits.where(~F.col("seed")).distinct()
    doubt = loose.select(*place, F.explode("patterns").alias("pattern")).join(patterns, ["kind", "pattern"]).groupBy(place).agg(F.sum(F.log1p(-F.least("trust", F.lit(0.999)))).alias("doubt"))
    by_place = doubt.select(*place, (1 - F.exp("doubt")).alias("trust")).where(F.col("trust") >= threshold)
    by_name = loose.join(instances, ["kind", "instance"]).select(*place, "trust")
    best = by_place.union(by_name).groupBy("doc_id", "row_key", "start", "end").agg(F.max(F.struct("trust", (-F.col("kind")).alias("kind"))).alias("b"))
    added = best.groupBy("doc_id", "row_key").agg(F.collect_list(F.struct((-F.col("b.kind")).alias("kind"), "start", "end")).alias("added"))
    scanned, added = scanned.alias("s"), added.alias("a")
    out = scanned.join(added, F.col("s.doc_id").eqNullSafe(F.col("a.doc_id")) & (F.col("s.row_key") == F.col("a.row_key")), "left").select("s.doc_id", "s.base", "s.hits", "a.added")
    names = F.array(*[F.lit(k) for k in KINDS])
    written = lambda spans: F.array_join(F.transform(F.array_sort(spans), lambda x: F.concat_ws(":", F.element_at(names, x["kind"] + 1), x["start"].cast("string"), x["end"].cast("string"))), ",")
    seeds = F.transform(F.filter("hits", lambda h: h["seed"]), lambda h: F.struct(h["kind"].alias("kind"), h["start"].alias("start"), h["end"].alias("end")))
    count = lambda i: F.size(F.filter("hits", lambda h: h["seed"] & (h["kind"] == i))).cast("long").alias(f"n_{KINDS[i]}")
    spans = F.when(F.col("added").isNull(), F.col("base")).otherwise(written(F.concat(seeds, "added")))
    return out.select("doc_id", *[count(i) for i in range(4)], F.sha2("base", 256).alias("base_sha256"), spans.alias("spans"), F.when(F.col("added").isNull(), 0).otherwise(F.size("added")).cast("long").alias("n_added"))


def op1_bootstrapped_private_data(spark: SparkSession, sf_dir: str) -> DataFrame:
    return find_private(read(spark, sf_dir, "documents"))
