"""Secret scans by corpus-wide ownership of candidate values, in SQL functions only."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

#: Fixed patterns of the base kinds, in the order listed; a match of assign passes with 8 characters in group 2.
ASSIGN = r"""(?i:(password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ACCESS = r"AKIA[A-Z0-9]{12,}"
HEX = r"[0-9a-f]{32,}"
LEAST_VALUE = 8
#: What a value may look like besides: a run of 20 token characters with a digit and letters of both cases.
VALUE, VALUE_HAS = r"[A-Za-z0-9+/_=-]{20,}", (r"[0-9]", r"[A-Z]", r"[a-z]")
#: Owners and repositories that a live credential is seen in, at most; a value of more is a copied example.
MOST_OWNERS, MOST_REPOSITORIES = 1, 2

_KINDS = ("assign", "access", "hex", "owned")
_SPAN = "array<struct<start:bigint,kind:int,end:bigint,h:bigint>>"


def _matches(text: Column, pattern: str, group: int) -> Column:
    """Array of (start, end, value) of a pattern's matches, in code points; value is the group's text."""
    whole, value = F.regexp_extract_all(text, F.lit(pattern), F.lit(0)), F.regexp_extract_all(text, F.lit(pattern), F.lit(group))
    between = F.split(text, pattern, -1)
    gap = F.transform(F.arrays_zip(F.slice(between, 1, F.size(whole)).alias("b"), whole.alias("w")), lambda x: (F.length(x["b"]) + F.length(x["w"])).cast("long"))
    return F.transform(
        F.arrays_zip(common.offsets(gap).alias("at"), gap.alias("g"), whole.alias("w"), value.alias("v")),
        lambda x: F.struct((x["at"] + x["g"] - F.length(x["w"])).alias("start"), (x["at"] + x["g"]).alias("end"), x["v"].alias("v")),
    )


def _spans(found: Column, kind: str) -> Column:
    return F.transform(found, lambda x: F.struct(x["start"].alias("start"), F.lit(_KINDS.index(kind)).alias("kind"), x["end"].alias("end"), F.xxhash64(x["v"]).alias("h"))).cast(_SPAN)


def _where(test: Column, spans: Column) -> Column:
    return F.when(test, spans).otherwise(F.array().cast(_SPAN))


def _joined(spans: Column) -> Column:
    names = F.array(*[F.lit(k) for k in _KINDS])
    return F.concat_ws(",", F.transform(spans, lambda s: F.concat_ws(":", F.element_at(names, s["kind"] + 1), s["start"].cast("string"), s["end"].cast("string"))))


def candidates(docs: DataFrame, owner: Column, repository: Column) -> DataFrame:
    """One row per document with its base spans and other values that look like secrets (arrays of start, kind, end, h)."""
    text = F.coalesce("text", F.lit(""))
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), owner.cast("string").alias("owner"), repository.cast("string").alias("repository"), text.alias("text"))
    assign = F.filter(_matches(F.col("text"), ASSIGN, 2), lambda x: F.length(x["v"]) >= LEAST_VALUE)
    rows = rows.select(
        "*",
        _where(F.col("text").rlike("(?i:passw|secret|token|api)"), _spans(assign, "assign")).alias("assign"),
        _where(F.contains("text", F.lit("AKIA")), _spans(_matches(F.col("text"), ACCESS, 0), "access")).alias("access"),
        _where(F.col("text").rlike(HEX), _spans(_matches(F.col("text"), HEX, 0), "hex")).alias("hex"),
        _where(F.col("text").rlike(VALUE), _spans(F.filter(_matches(F.col("text"), VALUE, 0), lambda x: x["v"].rlike(VALUE_HAS[0]) & x["v"].rlike(VALUE_HAS[1]) & x["v"].rlike(VALUE_HAS[2])), "owned")).alias("other"),
    )
    base = F.array_sort(F.concat("assign", "access", "hex"))
    rows = rows.select(
        "doc_id", "owner", "repository", F.xxhash64("text", F.col("doc_id").isNull()).alias("k2"), F.size("assign").cast("long").alias("n_assign"), F.size("access").cast("long").alias("n_access"),
        F.size("hex").cast("long").alias("n_hex"), base.alias("base"), "other",
    )
    return rows.withColumn("other", F.filter("other", lambda o: ~F.exists("base", lambda b: (b["start"] < o["end"]) & (o["start"] < b["end"]))))


def ownership(values: DataFrame) -> DataFrame:
    """(h, owner, repository) -> h, n_owners, n_repositories, distinct ones, counted in two steps so that a value with
    very many copies is summed before it is sent."""
    each = values.groupBy("h", "owner", "repository").agg(F.count("*").alias("n"))
    return each.groupBy("h").agg(F.count_distinct(F.coalesce("owner", F.lit("\0"))).alias("n_owners"), F.count_distinct(F.coalesce("owner", F.lit("\0")), F.coalesce("repository", F.lit("\0"))).alias("n_repositories"), F.sum("n").alias("n_seen"))


def scan(docs: DataFrame, owner: Column, repository: Column, most_owners: int = MOST_OWNERS, most_repositories: int = MOST_REPOSITORIES) -> DataFrame:
    """Base spans, and further values that only one owner holds, per document.

    Columns used: doc_id, text and those of owner and repository (null is an owner of its own). Returns doc_id,
    n_assign, n_access, n_hex, base_sha256, spans (kind:start:end by start, then kind), n_live and n_example (values
    of the document seen with few owners and repositories, or more). All base spans stay, whatever their ownership; a
    further value is added as kind `owned` if it is live. A null text is empty; repeated rows stay; a value repeated
    by rows alike counts for the same owner; an empty table gives an empty result.
    """
    rows = common.stored(candidates(docs, owner, repository))
    each = rows.select("doc_id", "k2", "owner", "repository", F.explode(F.concat("base", "other")).alias("s")).select("*", F.col("s.h").alias("h"))
    known = ownership(each)
    judged = common.dealt_join(each, known, "h").withColumn("live", (F.col("n_owners") <= most_owners) & (F.col("n_repositories") <= most_repositories))
    key = F.coalesce("doc_id", F.lit(-(2**62)))
    per = judged.groupBy(key.alias("k1_"), F.col("k2").alias("k2_")).agg(
        F.collect_set(F.when(F.col("live") & (F.col("s.kind") == _KINDS.index("owned")), F.col("s"))).alias("added"),
        F.size(F.collect_set(F.when(F.col("live"), F.col("s")))).cast("long").alias("n_live"), F.size(F.collect_set(F.when(~F.col("live"), F.col("s")))).cast("long").alias("n_example"),
    )
    out = rows.join(per, (key == F.col("k1_")) & (F.col("k2") == F.col("k2_")), "left")
    every = F.array_sort(F.concat("base", F.coalesce("added", F.array().cast(_SPAN))))
    return out.select("doc_id", "n_assign", "n_access", "n_hex", F.sha2(_joined(F.col("base")), 256).alias("base_sha256"), _joined(every).alias("spans"), F.coalesce("n_live", F.lit(0)).alias("n_live"), F.coalesce("n_example", F.lit(0)).alias("n_example"))


def op6_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.table(spark, sf_dir, "documents")
    return scan(docs, F.col("source"), F.concat_ws("/", "source", "lang"))
