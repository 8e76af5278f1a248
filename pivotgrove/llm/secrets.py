"""Operator 8: secrets, and how widely the corpus owns each of them. DataFrame functions only.

Fixed shapes find candidates with their places: the pieces between matches and the matches themselves, in
turn, add up to offsets. Every candidate's hash is counted over the whole corpus by distinct repository and
distinct owner, after a count within each: a value that many owners, or very many repositories of one, carry is
a copied example, any other is live-looking. A broader shape, a long run that mixes digits with letters of both cases, is added to
the spans only where its owners are few.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from pivotgrove.llm.tables import read
from pivotgrove.runtime import materialise

KINDS = ("assign", "access", "hex", "mixed")
#: The shapes. Of `assign` the second group must be long enough after the match, without a retry.
SHAPES = {
    "assign": r"""((?i:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""",
    "access": r"AKIA[A-Z0-9]{12,}",
    "hex": r"[0-9a-f]{32,}",
    "mixed": r"(?<![A-Za-z0-9+/_-])(?=[A-Za-z+/_-]*[0-9])(?=[A-Z0-9+/_-]*[a-z])(?=[a-z0-9+/_-]*[A-Z])[A-Za-z0-9+/_-]{24,}+",
}
VALUE_LENGTH = 8
MAX_OWNERS, MAX_REPOSITORIES = 2, 8
RUN = 256  #: matches whose places are added up in one go


def _places(text: Column, kind: str) -> Column:
    """array<struct<kind, start, end, value>> of the matches of one shape, in code points."""
    shape = F.lit(SHAPES[kind])
    hits = F.regexp_extract_all(text, shape, F.lit(0))
    gaps = F.split(text, SHAPES[kind], -1)
    each = F.zip_with(hits, F.slice(gaps, 1, F.size(hits)), lambda h, g: F.struct(h.alias("hit"), F.char_length(g).cast("long").alias("gap")))  # gap i stands before match i
    # Runs of bounded length: first what each adds, then where each begins, then the places inside it.
    runs = F.transform(F.sequence(F.lit(0), F.floor((F.size(hits) - 1) / RUN).cast("int")), lambda i: F.slice(each, i * RUN + 1, RUN))
    zero = F.lit(0).cast("long")
    adds = F.transform(runs, lambda r: F.aggregate(r, zero, lambda at, x: at + x["gap"] + F.char_length(x["hit"])))
    begins = F.aggregate(adds, F.struct(zero.alias("at"), F.array().cast("array<bigint>").alias("out")), lambda s, n: F.struct((s["at"] + n).alias("at"), F.concat(s["out"], F.array(s["at"])).alias("out")), lambda s: s["out"])
    inside = lambda run, begin: F.aggregate(
        run,
        F.struct(begin.alias("at"), F.array().cast("array<struct<kind:int,start:bigint,end:bigint,value:string>>").alias("out")),
        lambda s, x: F.struct(
            (s["at"] + x["gap"] + F.char_length(x["hit"])).alias("at"),
            F.concat(s["out"], F.array(F.struct(F.lit(KINDS.index(kind)).alias("kind"), (s["at"] + x["gap"]).alias("start"), (s["at"] + x["gap"] + F.char_length(x["hit"])).alias("end"), x["hit"].alias("value")))).alias("out"),
        ),
        lambda s: s["out"],
    )
    start = F.flatten(F.zip_with(runs, begins, inside))
    if kind == "assign":
        kept = F.filter(start, lambda x: F.char_length(F.regexp_extract(x["value"], SHAPES[kind], 2)) >= VALUE_LENGTH)
        start = F.transform(kept, lambda x: F.struct(x["kind"].alias("kind"), x["start"].alias("start"), x["end"].alias("end"), F.regexp_extract(x["value"], SHAPES[kind], 2).alias("value")))
    none = F.array().cast("array<struct<kind:int,start:bigint,end:bigint,value:string>>")
    return F.when(text.rlike(SHAPES[kind]), start).otherwise(none)


def candidates(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", repository: str = "source", owner: str | None = None) -> DataFrame:
    """(doc_id, row_key, repository, owner, found): found lists the places of every shape, a null text has none.

    The row_key is the hash of a text with candidates or without a doc_id, else 0: with the doc_id it names the text.
    Without an owner column the owner is the repository's name before its first slash.
    """
    body = F.coalesce(F.col(text), F.lit(""))
    repo = F.coalesce(F.col(repository).cast("string"), F.lit("")) if repository in docs.columns else F.lit("")
    who = F.coalesce(F.col(owner).cast("string"), F.lit("")) if owner else F.split_part(repo, F.lit("/"), F.lit(1))
    base = docs.select(F.col(doc_id).cast("long").alias("doc_id"), body.alias("text"), repo.alias("repository"), who.alias("owner"))
    found = F.concat(*[_places(F.col("text"), k) for k in KINDS])
    key = F.when((F.size("found") > 0) | F.col("doc_id").isNull(), F.xxhash64("text")).otherwise(F.lit(0).cast("long"))
    return base.withColumn("found", found).select("doc_id", key.alias("row_key"), "repository", "owner", "found")


def ownership(found: DataFrame) -> DataFrame:
    """(value_hash, documents, repositories, owners) of every candidate value; a hot value meets no task whole."""
    one = found.where(F.size("found") > 0).select("repository", "owner", F.explode("found").alias("f")).select("repository", "owner", F.xxhash64("f.value").alias("value_hash"))
    by_place = one.groupBy("value_hash", "repository", "owner").agg(F.count("*").alias("n"))
    by_owner = by_place.groupBy("value_hash", "owner").agg(F.sum("n").alias("n"), F.count("*").alias("repositories"))
    repositories = by_place.groupBy("value_hash", "repository").agg(F.lit(1).alias("one")).groupBy("value_hash").agg(F.count("*").alias("repositories"))
    return by_owner.groupBy("value_hash").agg(F.sum("n").alias("occurrences"), F.count("*").alias("owners")).join(repositories, "value_hash")


def find_secrets(docs: DataFrame, max_owners: int = MAX_OWNERS, max_repositories: int = MAX_REPOSITORIES, doc_id: str = "doc_id", text: str = "text", repository: str = "source", owner: str | None = None) -> DataFrame:
    """Per row of docs: doc_id, n_assign, n_access, n_hex, base_sha256, spans, n_live, n_copied, `found` and row_key.

    `found` holds every span with its verdict. A null or empty text has none (and the hash of no bytes).
    Repeated rows get equal results, rows that share a doc_id or have none their own text's, an empty table gives no rows, other columns are ignored, a repository or
    owner that is null counts as the empty name. Texts of any length are read whole.
    """
    scanned = materialise(candidates(docs, doc_id, text, repository, owner), "secret-candidates")
    copied = ownership(scanned).where((F.col("owners") > max_owners) | (F.col("repositories") > max_repositories)).select("value_hash", F.lit(True).alias("copied"))
    each = scanned.where(F.size("found") > 0).select("doc_id", "row_key", F.explode("found").alias("f")).select("doc_id", "row_key", "f.kind", "f.start", "f.end", F.xxhash64("f.value").alias("value_hash")).distinct()
    # Copied values are few; a hot one among them meets its rows in parts, as a skewed side of this join is split.
    judged = each.join(copied, "value_hash", "left").withColumn("copied", F.coalesce("copied", F.lit(False)))
    by_row = judged.groupBy("doc_id", "row_key").agg(F.array_sort(F.collect_list(F.struct("start", "kind", "end", "copied"))).alias("judged"))
    rows, by_row = scanned.select("doc_id", "row_key").alias("r"), by_row.alias("b")
    same = F.col("r.doc_id").eqNullSafe(F.col("b.doc_id")) & (F.col("r.row_key") == F.col("b.row_key"))
    out = rows.join(by_row, same, "left").select("r.doc_id", "r.row_key", "b.judged")
    none = F.array().cast("array<struct<start:bigint,kind:int,end:bigint,copied:boolean>>")
    out = out.select("doc_id", "row_key", F.coalesce("judged", none).alias("judged"))
    base = F.filter("judged", lambda x: x["kind"] < 3)
    # A broader span counts when few own it and no base span holds it.
    more = F.filter("judged", lambda x: (x["kind"] < 3) | (~x["copied"] & ~F.exists(base, lambda b: (b["start"] < x["end"]) & (x["start"] < b["end"]))))
    names = F.array(*[F.lit(k) for k in KINDS])
    written = lambda spans: F.array_join(F.transform(spans, lambda x: F.concat_ws(":", F.element_at(names, x["kind"] + 1), x["start"].cast("string"), x["end"].cast("string"))), ",")
    of_kind = lambda i: lambda x: x["kind"] == i  # noqa: E731 (a second parameter of the inner one would be the place in the array)
    count = lambda test: F.size(F.filter("found", test)).cast("long")
    return (
        out.select("doc_id", "row_key", base.alias("base"), more.alias("found"))
        .select(
            "doc_id",
            *[count(of_kind(i)).alias(f"n_{KINDS[i]}") for i in range(3)],
            F.sha2(written(F.col("base")), 256).alias("base_sha256"),
            written(F.col("found")).alias("spans"),
            count(lambda x: ~x["copied"]).alias("n_live"),
            count(lambda x: x["copied"]).alias("n_copied"),
            "found",
            "row_key",
        )
    )


def op8_secret_ownership(spark: SparkSession, sf_dir: str) -> DataFrame:
    return find_secrets(read(spark, sf_dir, "documents")).drop("found", "row_key")
