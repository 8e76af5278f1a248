"""The corpus pipeline: toxic documents go, one of each near-copy group stays, secrets are masked, the rest is packed."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from pivotgrove.llm import occurrence_join, packing, secrets, toxicity
from pivotgrove.llm.tables import read
from pivotgrove.runtime import discard, materialise

MASK = "[secret]"
NEAR_WORDS, NEAR_PERCENT = 5, 80


#: From here on lie the stand-ins for null doc_ids: the hash of the text, above every other id.
NO_ID = 1 << 62


def identity(text_hash: Column) -> Column:
    """The doc_id; where it is null, a stand-in from the text alone: rows without an id are one only if they say the same."""
    return F.coalesce(F.col("doc_id").cast("long"), F.shiftrightunsigned(text_hash, 2) + F.lit(NO_ID))


def text_hash() -> Column:
    return F.xxhash64(F.coalesce("text", F.lit("")))


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the factorisation machine calls toxic go. Repeated doc_ids go together, any of them toxic; without one a text goes by itself.

    Where nothing is labelled, nothing goes.
    """
    judged = toxicity.score(docs, toxicity.fit(docs, read(spark, sf_dir, "labels")), keyed=True)
    toxic = judged.where("predicted = 1").select(identity(F.col("row_key")).alias("_identity")).distinct()
    return docs.withColumn("_identity", identity(text_hash())).join(toxic, "_identity", "left_anti").select(docs.columns)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group that links join, the document of smallest doc_id stays (all its rows, should the id repeat).

    Rows without a doc_id come after all others, and of equal texts among them one stays.
    """
    named = docs.withColumn("_identity", identity(text_hash()))
    judged = occurrence_join.jaccard_components(named.select(F.col("_identity").alias("doc_id"), "text"), NEAR_WORDS, NEAR_PERCENT)
    gone = judged.where("component_id != doc_id").select(F.col("doc_id").alias("_identity")).distinct()
    left = named.join(gone, "_identity", "left_anti")
    return left.where("doc_id is not null").union(left.where("doc_id is null").dropDuplicates(["_identity"])).select(docs.columns)


def mask_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every document stays; the spans of its secrets are replaced by the mask, copied examples' too, and n_chars follows.

    Rows that share a doc_id, or have none, are masked each by its own text's spans; a null text stays null.
    """
    found = secrets.find_secrets(docs).where(F.size("found") > 0)
    # Overlapping spans are masked as one: a span begins where none before it reaches.
    spans = F.aggregate(
        "found",
        F.array().cast("array<struct<start:bigint,end:bigint>>"),
        lambda out, x: F.when(
            (F.size(out) > 0) & (F.coalesce(F.try_element_at(out, F.lit(-1))["end"], F.lit(-1).cast("long")) > x["start"]),
            F.concat(F.slice(out, 1, F.size(out) - 1), F.array(F.struct(F.try_element_at(out, F.lit(-1))["start"].alias("start"), F.greatest(F.try_element_at(out, F.lit(-1))["end"], x["end"]).alias("end")))),
        ).otherwise(F.concat(out, F.array(F.struct(x["start"].alias("start"), x["end"].alias("end"))))),
    )
    # The spans belong to a text: rows that share a doc_id, or have none, are told apart by its hash.
    spans = found.groupBy("doc_id", "row_key").agg(F.first("found").alias("found")).select(F.col("doc_id").alias("_doc_id"), "row_key", spans.alias("spans"))
    joined = docs.join(spans, F.col("doc_id").cast("long").eqNullSafe(F.col("_doc_id")) & (text_hash() == F.col("row_key")), "left")
    masked = F.aggregate(
        "spans",
        F.struct(F.lit(0).cast("long").alias("at"), F.lit("").alias("out")),
        lambda s, x: F.struct(x["end"].alias("at"), F.concat(s["out"], F.substring(F.col("text"), (s["at"] + 1).cast("int"), (x["start"] - s["at"]).cast("int")), F.lit(MASK)).alias("out")),
        lambda s: F.concat(s["out"], F.substring(F.col("text"), (s["at"] + 1).cast("int"), F.lit(2147483647))),
    )
    out = joined.withColumn("masked", F.when(F.col("spans").isNotNull(), masked))
    new = {"text": F.coalesce("masked", "text")}
    if "n_chars" in docs.columns:
        new["n_chars"] = F.when(F.col("masked").isNull(), F.col("n_chars")).otherwise(F.char_length("masked")).cast(docs.schema["n_chars"].dataType)
    return out.select(*[new[c].alias(c) if c in new else c for c in docs.columns])


def pack_tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The pieces of every document in windows of tokens."""
    return packing.pack(docs)


STAGES: list[tuple[str, Callable[[SparkSession, DataFrame, str], DataFrame]]] = [
    ("toxicity", drop_toxic),
    ("near_copies", drop_near_copies),
    ("secrets", mask_secrets),
    ("packing", pack_tokens),
]

#: Learned scores, graph components and tokenizers are beyond SQL; tests hold run() against plain Python.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        older, docs = docs, materialise(stage(spark, docs, sf_dir), f"pipeline-{name}")
        discard(older)
    return STAGES[-1][1](spark, docs, sf_dir)
