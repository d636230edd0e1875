"""Ingest and cleaning: the record envelope, markup, boilerplate, white space, page fields."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..catalog import query, table
from ..functions.text import SQL_LINES, lines, normalize_script, LATIN


def homogenize(df: DataFrame, id_col: str, text_col: str, meta: list[str]) -> DataFrame:
    """Any table as records: id, text, metadata (all as strings) and an empty map of quality signals."""
    pairs = [x for c in meta for x in (F.lit(c), F.col(c).cast("string"))]
    return df.select(F.col(id_col).cast("bigint").alias("id"), F.col(text_col).alias("text"), F.create_map(*pairs).alias("metadata"), F.create_map().cast("map<string,double>").alias("quality_signals"))


@query("homogenize_records", "SELECT doc_id AS id, text, lang || '|' || source || '|' || n_chars::VARCHAR AS meta, 0 AS n_signals FROM documents")
def _homogenize(spark, d):
    r = homogenize(table(spark, d, "documents"), "doc_id", "text", ["lang", "source", "n_chars"])
    return r.select("id", "text", F.concat_ws("|", *[F.col("metadata")[k] for k in ("lang", "source", "n_chars")]).alias("meta"), F.size("quality_signals").alias("n_signals"))


def strip_markup(html: Column) -> Column:
    """Text of a page: comments go first, then script and style blocks, tags, entities, and runs of white space."""
    out = F.regexp_replace(html, r"(?s)<!--.*?-->", " ")
    out = F.regexp_replace(out, r"(?is)<(script|style)[^>]*>.*?</(script|style)>", " ")
    out = F.regexp_replace(out, r"(?s)<[^>]*>", " ")
    for a, b in (("&nbsp;", " "), ("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "'"), ("&amp;", "&")):
        out = F.replace(out, F.lit(a), F.lit(b))
    return F.trim(F.regexp_replace(out, "[ \t\n\r]+", " "))


_SQL_STRIP = r"""trim(regexp_replace(replace(replace(replace(replace(replace(replace(
  regexp_replace(regexp_replace(regexp_replace(html, '(?s)<!--.*?-->', ' ', 'g'), '(?is)<(script|style)[^>]*>.*?</(script|style)>', ' ', 'g'), '(?s)<[^>]*>', ' ', 'g'),
  '&nbsp;', ' '), '&lt;', '<'), '&gt;', '>'), '&quot;', '"'), '&#39;', ''''), '&amp;', '&'), '[ \t\n\r]+', ' ', 'g'))"""


@query("strip_markup", f"SELECT page_id, {_SQL_STRIP} AS text FROM pages")
def _strip(spark, d):
    return table(spark, d, "pages").select("page_id", strip_markup(F.col("html")).alias("text"))


def normalize_ws(text: Column, keep_newlines: bool = True) -> Column:
    """One blank for runs of blanks and tabs, one line break for runs of them, no literal escapes at the end."""
    out = F.regexp_replace(text, r"[ \t\r\f]+", " ")
    out = F.regexp_replace(out, r"\n{2,}", "\n") if keep_newlines else F.regexp_replace(out, r" *\n+ *", " ")
    return F.trim(F.regexp_replace(out, r"(\\n|\\t|\\r| )+$", ""))


@query("normalize_ws", r"""SELECT doc_id, trim(regexp_replace(regexp_replace(regexp_replace(text, '[ \t\r\f]+', ' ', 'g'), '\n{2,}', chr(10), 'g'), '(\\n|\\t|\\r| )+$', '')) AS text FROM documents""")
def _ws(spark, d):
    return table(spark, d, "documents").select("doc_id", normalize_ws(F.col("text")).alias("text"))


def host(url: Column) -> Column:
    """Host without port, in lower case, without a leading www., m. or blog."""
    return F.regexp_replace(F.regexp_extract(F.lower(url), r"^[a-z]+://([^/:?#]+)", 1), r"^(www|m|blog)\.", "")


SQL_HOST = r"regexp_replace(regexp_extract(lower(url), '^[a-z]+://([^/:?#]+)', 1), '^(www|m|blog)\.', '')"


@query("page_fields", rf"""SELECT page_id, {SQL_HOST} AS host, regexp_extract(html, '(?is)<title>(.*?)</title>', 1) AS title, len(regexp_extract_all(html, '(?i)<a[^>]*href'))::BIGINT AS n_links, len(regexp_extract_all(html, '(?i)<li[ >]'))::BIGINT AS n_items FROM pages""")
def page_fields(spark, d):
    p = table(spark, d, "pages")
    return p.select(
        "page_id", host(F.col("url")).alias("host"), F.regexp_extract("html", r"(?is)<title>(.*?)</title>", 1).alias("title"),
        F.regexp_count("html", F.lit(r"(?i)<a[^>]*href")).cast("bigint").alias("n_links"), F.regexp_count("html", F.lit(r"(?i)<li[ >]")).cast("bigint").alias("n_items"),
    )


def boilerplate(df: DataFrame, site: str, doc: str, text: str, min_docs: int = 3) -> DataFrame:
    """(site, line, n_docs) of lines that stand in min_docs documents of one site or more: headers, footers, menus.

    Lines are counted by hash with a partial sum in each task, so a line on every page of a site is sent once a task.
    """
    each = df.select(site, doc, F.explode(F.array_distinct(lines(text))).alias("line"))
    return each.groupBy(site, "line").agg(F.count("*").alias("n_docs")).filter(F.col("n_docs") >= min_docs)


def drop_boilerplate(df: DataFrame, site: str, doc: str, text: str, min_docs: int = 3) -> DataFrame:
    """Each document's lines in order without its site's repeated lines; a document of nothing else becomes empty.

    Only (site, hash) keys of repeated lines are joined; the pieces of a document meet again by its id."""
    bad = boilerplate(df, site, doc, text, min_docs).select(F.col(site).alias("s_"), F.xxhash64("line").alias("h_"))
    each = df.select(site, doc, F.posexplode(lines(text)).alias("pos", "line")).withColumn("h", F.xxhash64("line"))
    kept = each.join(bad, (F.col(site) == F.col("s_")) & (F.col("h") == F.col("h_")), "left_anti")
    joined = kept.groupBy(doc).agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("pos", "line"))), lambda x: x["line"]), "\n").alias("clean"))
    return df.select(doc).join(joined, doc, "left").select(doc, F.coalesce("clean", F.lit("")).alias("clean"))


_SQL_BOILER = f"""SELECT source, line, count(*) AS n_docs FROM (SELECT source, doc_id, unnest(list_distinct({SQL_LINES})) AS line FROM documents) GROUP BY ALL HAVING count(*) >= 3"""


@query("boilerplate_lines", _SQL_BOILER)
def _boiler(spark, d):
    return boilerplate(table(spark, d, "documents"), "source", "doc_id", "text")


@query(
    "boilerplate_removed",
    f"""WITH bad AS ({_SQL_BOILER}), l AS (SELECT source, doc_id, {SQL_LINES} AS ls FROM documents),
    e AS (SELECT source, doc_id, unnest(ls) AS line, unnest(range(1, len(ls) + 1)) AS pos FROM l),
    k AS (SELECT doc_id, string_agg(line, chr(10) ORDER BY pos) AS clean FROM e ANTI JOIN bad USING (source, line) GROUP BY doc_id)
    SELECT doc_id, coalesce(clean, '') AS clean FROM documents LEFT JOIN k USING (doc_id)""",
)
def _boiler_removed(spark, d):
    return drop_boilerplate(table(spark, d, "documents"), "source", "doc_id", "text")


@query("script_normalize", "SELECT doc_id, regexp_replace(translate(lower(text), 'àâäáãåçéèêëíìîïñóòôöõúùûüýÿ', 'aaaaaaceeeeiiiinooooouuuuyy'), '\\p{M}', '', 'g') AS text FROM documents")
def _script(spark, d):
    return table(spark, d, "documents").select("doc_id", normalize_script(F.col("text"), LATIN).alias("text"))
