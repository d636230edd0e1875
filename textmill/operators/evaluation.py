"""Evaluation measures: multiple choice, exact match, verifiable instructions, BLEU, error rates, leaderboards, votes."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..catalog import query, table
from ..functions.text import h28, ratio, sql_h28, sql_ratio, words

_W = "list_filter(string_split_regex(lower({}), '[ \\t\\n\\r]+'), lambda x: x <> '')"
#: Items of a block in which options and examples are drawn; blocks are by hash, as many as the table needs.
BLOCK = 64
_SQL_BLOCKS = f"(SELECT greatest(1, (count(*) + {BLOCK - 1}) // {BLOCK}) FROM benchmark)"


def blocked(items: DataFrame) -> Column:
    """An item's hash block; blocks hold about BLOCK items however many there are, so a join of blocks is linear."""
    return h28(F.col("item_id").cast("string")) % max(1, -(-items.count() // BLOCK))


# Options of a continuation item: its own second half and three others picked by hash; the score of an option is a hash
# stand-in for a log-likelihood that favours words shared with the first half.
_SQL_MCQ = f"""(SELECT i.item_id, o.item_id AS option_id, o.rest AS option, i.context, (i.item_id = o.item_id) AS gold FROM
  (SELECT item_id, array_to_string(w[1:len(w)//2], ' ') AS context FROM (SELECT item_id, {_W.format('text')} AS w FROM benchmark)) i
  JOIN (SELECT item_id, array_to_string(w[len(w)//2+1:], ' ') AS rest FROM (SELECT item_id, {_W.format('text')} AS w FROM benchmark)) o
    ON {sql_h28('i.item_id::VARCHAR')} % {_SQL_BLOCKS} = {sql_h28('o.item_id::VARCHAR')} % {_SQL_BLOCKS}
  QUALIFY row_number() OVER (PARTITION BY i.item_id ORDER BY (i.item_id <> o.item_id)::INT, {sql_h28("i.item_id::VARCHAR || '-' || o.item_id::VARCHAR")}, o.item_id) <= 4)"""


def continuation_mcq(items: DataFrame, k: int = 4) -> DataFrame:
    """(item_id, option_id, option, context, gold): an item's own second half and others of its block."""
    w = items.select("item_id", words("text").alias("w"), blocked(items).alias("block"))
    half = F.floor(F.size("w") / 2).cast("int")
    a = w.select("item_id", F.array_join(F.slice("w", F.lit(1), half), " ").alias("context"), "block")
    b = w.select("block", F.col("item_id").alias("option_id"), F.array_join(F.slice("w", half + 1, F.size("w")), " ").alias("option"))
    order = Window.partitionBy("item_id").orderBy((F.col("item_id") != F.col("option_id")).cast("int"), h28(F.concat_ws("-", "item_id", "option_id")), "option_id")
    j = a.join(b, "block").withColumn("rn", F.row_number().over(order)).filter(F.col("rn") <= k)
    return j.select("item_id", "option_id", "option", "context", (F.col("item_id") == F.col("option_id")).alias("gold"))


@query("continuation_mcq", f"SELECT * FROM {_SQL_MCQ}")
def _mcq(spark, d):
    return continuation_mcq(table(spark, d, "benchmark"))


_SQL_LL = f"(SELECT *, -({sql_h28('option')} % 1000) / 100.0::DOUBLE - length(option) / 10.0::DOUBLE AS ll FROM {_SQL_MCQ})"


def _scored(spark, d) -> DataFrame:
    return _mcq(spark, d).withColumn("ll", -(h28(F.col("option")) % 1000) / 100.0 - F.length("option") / 10.0)


for _name, _s, _sql in (("mcq_accuracy", lambda: F.col("ll"), "ll"), ("mcq_accuracy_norm", lambda: F.col("ll") / F.length("option"), "ll / length(option)")):

    def _accuracy(spark, d, score=_s):
        g = _scored(spark, d).groupBy("item_id").agg(F.max_by("gold", F.struct(F.round(score(), 9), -F.col("option_id"))).alias("ok"))
        return g.agg(F.count("*").alias("n"), F.count_if("ok").alias("right"), F.round(F.avg(F.col("ok").cast("int")), 6).alias("accuracy"))

    query(_name, f"SELECT count(*) AS n, count(*) FILTER (ok) AS right, round(avg(ok::INT), 6) AS accuracy FROM (SELECT item_id, arg_max(gold, (round({_sql}, 9), -option_id)) AS ok FROM {_SQL_LL} GROUP BY item_id)")(_accuracy)


@query("exact_match", "SELECT count(*) AS n, count(*) FILTER (last IS NOT NULL AND last <> '') AS answered FROM (SELECT regexp_extract_all(text, '[0-9]+')[-1] AS last FROM documents)")
def exact_match(spark, d):
    """Flexible extraction: the last number of an answer."""
    last = F.try_element_at(F.regexp_extract_all("text", F.lit("[0-9]+"), F.lit(0)), F.lit(-1))
    return table(spark, d, "documents").agg(F.count("*").alias("n"), F.count(last).alias("answered"))


@query("kshot_prompts", f"SELECT a.item_id, string_agg(b.text, chr(10) ORDER BY {sql_h28("a.item_id::VARCHAR || ':' || b.item_id::VARCHAR")}, b.item_id) AS shots FROM benchmark a JOIN LATERAL (SELECT b.item_id, b.text FROM benchmark b WHERE b.item_id <> a.item_id AND {sql_h28('a.item_id::VARCHAR')} % {_SQL_BLOCKS} = {sql_h28('b.item_id::VARCHAR')} % {_SQL_BLOCKS} ORDER BY {sql_h28("a.item_id::VARCHAR || ':' || b.item_id::VARCHAR")}, b.item_id LIMIT 3) b ON true GROUP BY a.item_id")
def kshot(spark, d, k: int = 3):
    b = table(spark, d, "benchmark")
    b = b.withColumn("block", blocked(b))
    j = b.select("item_id", "block").join(b.select(F.col("item_id").alias("o"), "text", "block"), "block").filter("item_id <> o").withColumn("h", h28(F.concat_ws(":", "item_id", "o")))
    top = j.withColumn("rn", F.row_number().over(Window.partitionBy("item_id").orderBy("h", "o"))).filter(F.col("rn") <= k)
    return top.groupBy("item_id").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("rn", "text"))), lambda x: x["text"]), "\n").alias("shots"))


@query("macro_micro", "WITH s AS (SELECT source, avg(quality) AS a, count(*) AS n FROM documents JOIN labels USING (doc_id) GROUP BY source) SELECT round(avg(a), 6) AS macro, round(sum(a * n) / sum(n), 6) AS micro FROM s")
def macro(spark, d):
    s = table(spark, d, "documents").join(table(spark, d, "labels"), "doc_id").groupBy("source").agg(F.avg("quality").alias("a"), F.count("*").alias("n"))
    return s.agg(F.round(F.avg("a"), 6).alias("macro"), F.round(F.sum(F.col("a") * F.col("n")) / F.sum("n"), 6).alias("micro"))


#: Kinds of verifiable instructions as (name, Spark test, the same in SQL).
CHECKS = (
    ("min_words", lambda t: F.size(words(t)) >= 20, f"len({_W.format('text')}) >= 20"), ("max_words", lambda t: F.size(words(t)) <= 200, f"len({_W.format('text')}) <= 200"),
    ("one_line", lambda t: ~F.contains(t, F.lit("\n")), "NOT contains(text, chr(10))"), ("all_lower", lambda t: t == F.lower(t), "text = lower(text)"), ("all_upper", lambda t: t == F.upper(t), "text = upper(text)"),
    ("no_comma", lambda t: ~F.contains(t, F.lit(",")), "NOT contains(text, ',')"), ("ends_stop", lambda t: t.rlike("[.]$"), "regexp_matches(text, '[.]$')"), ("starts_capital", lambda t: t.rlike("^[A-ZÀ-Þ]"), "regexp_matches(text, '^[A-ZÀ-Þ]')"),
    ("quoted", lambda t: t.rlike('^".*"$'), "regexp_matches(text, '^\".*\"$')"), ("has_digit", lambda t: t.rlike("[0-9]"), "regexp_matches(text, '[0-9]')"), ("bullets", lambda t: t.rlike("(?m)^[*-] "), "regexp_matches(text, '(?m)^[*-] ')"),
    ("title_marks", lambda t: t.rlike("<<.*>>"), "regexp_matches(text, '<<.*>>')"), ("placeholder", lambda t: t.rlike(r"\[[^\]]*\]"), r"regexp_matches(text, '\[[^\]]*\]')"), ("postscript", lambda t: t.rlike("P[.]S[.]"), "regexp_matches(text, 'P[.]S[.]')"),
    ("sentences", lambda t: F.regexp_count(t, F.lit("[.!?]+")) >= 2, "len(regexp_extract_all(text, '[.!?]+')) >= 2"), ("letter_frequency", lambda t: F.regexp_count(F.lower(t), F.lit("e")) >= 5, "len(regexp_extract_all(lower(text), 'e')) >= 5"),
    ("separator", lambda t: F.contains(t, F.lit("***")), "contains(text, '***')"), ("keyword", lambda t: F.array_contains(words(t), F.lit("the")), f"list_contains({_W.format('text')}, 'the')"), ("forbidden", lambda t: ~F.contains(t, F.lit("!!")), "NOT contains(text, '!!')"),
    ("lines", lambda t: F.size(F.split(t, "\n")) >= 2, "len(string_split(text, chr(10))) >= 2"), ("highlighted", lambda t: t.rlike(r"\*[^*\n]+\*"), r"regexp_matches(text, '\*[^*\n]+\*')"), ("section", lambda t: t.rlike("(?m)^# "), "regexp_matches(text, '(?m)^# ')"),
    ("question", lambda t: F.contains(t, F.lit("?")), "contains(text, '?')"), ("unique_floor", lambda t: F.size(F.array_distinct(words(t))) * 2 >= F.size(words(t)), f"len(list_distinct({_W.format('text')})) * 2 >= len({_W.format('text')})"), ("brief", lambda t: F.length(t) <= 500, "length(text) <= 500"),
)


@query("verifiable_instructions", "SELECT * FROM (" + " UNION ALL ".join(f"SELECT '{n}' AS kind, count(*) AS n, count(*) FILTER ({s}) AS passed FROM conversations WHERE role = 'assistant'" for n, _, s in CHECKS) + ")")
def verify(spark, d):
    """Passes of each kind of check over all answers: one scan, one row a kind."""
    a = table(spark, d, "conversations").filter("role = 'assistant'")
    s = a.agg(F.count("*").alias("n"), *[F.count_if(f(F.col("text"))).alias(n) for n, f, _ in CHECKS])
    return s.unpivot("n", [n for n, _, _ in CHECKS], "kind", "passed").select("kind", "n", "passed")


def bleu(pairs: DataFrame, by: str) -> DataFrame:
    """Corpus BLEU by group: clipped 1-4-gram precisions and the brevity penalty. Grams of a pair meet by (id, n, gram)."""

    def counts(col: str) -> DataFrame:
        w = pairs.select(by, "id", F.split(col, " ").alias("w")).select(by, "id", "w", F.explode(F.sequence(F.lit(1), F.lit(4))).alias("n")).filter("size(w) >= n")
        g = w.select(by, "id", "n", F.explode(F.transform(F.sequence(F.lit(1), F.size("w") - F.col("n") + 1), lambda i: F.array_join(F.slice(F.col("w"), i, F.col("n")), " "))).alias("g"))
        return g.groupBy(by, "id", "n", "g").agg(F.count("*").alias(f"c_{col}"))

    m = counts("hyp").join(counts("ref"), [by, "id", "n", "g"], "left").groupBy(by, "n").agg(F.sum(F.least("c_hyp", F.coalesce("c_ref", F.lit(0)))).alias("hit"), F.sum("c_hyp").alias("all"))
    p = m.groupBy(by).agg(F.exp(F.avg(F.log(F.when(F.col("hit") > 0, F.col("hit") / F.col("all"))))).alias("gm"), F.count_if(F.col("hit") > 0).alias("k"))
    lens = pairs.groupBy(by).agg(F.sum(F.size(F.split("hyp", " "))).alias("h"), F.sum(F.size(F.split("ref", " "))).alias("r"))
    bp = F.when(F.col("h") >= F.col("r"), 1.0).otherwise(F.exp(1 - F.col("r") / F.col("h")))
    return p.join(lens, by).select(by, F.round(F.when(F.col("k") == 4, 100 * bp * F.col("gm")).otherwise(0.0), 4).alias("bleu"))


#: Perturbations of a reference that stand for systems: every word whose hash is 0 modulo the rate is dropped, cut to
#: three letters, doubled, or cut to its first letter.
SYSTEMS = {"drop": (10, ""), "cut": (6, "3"), "double": (8, "2"), "initial": (5, "1")}
_REF = "(SELECT item_id AS id, string_split(text, ' ') AS w, text AS ref FROM benchmark)"


def _sql_system(name: str) -> str:
    rate = SYSTEMS[name][0]
    new = {"drop": "NULL", "cut": "substr(w[i], 1, 3)", "double": "w[i] || ' ' || w[i]", "initial": "substr(w[i], 1, 1)"}[name]
    return f"SELECT '{name}' AS system, id, ref, array_to_string(list_filter(list_transform(range(1, len(w) + 1), lambda i: CASE WHEN {sql_h28(f"'{name}' || id::VARCHAR || '-' || i::VARCHAR")} % {rate} = 0 THEN {new} ELSE w[i] END), lambda x: x IS NOT NULL), ' ') AS hyp FROM {_REF}"


_SQL_HYPS = "(" + " UNION ALL ".join(_sql_system(n) for n in SYSTEMS) + ")"


def perturb(name: str, rate: int, new):
    return lambda x, i: F.when(h28(F.concat(F.lit(name), F.concat_ws("-", "id", i + 1))) % rate == 0, new(x)).otherwise(x)


def hypotheses(items: DataFrame) -> DataFrame:
    out = None
    for name, (rate, _) in SYSTEMS.items():
        new = {"drop": lambda x: F.lit(None).cast("string"), "cut": lambda x: F.substring(x, 1, 3), "double": lambda x: F.concat_ws(" ", x, x), "initial": lambda x: F.substring(x, 1, 1)}[name]
        w = items.select(F.col("item_id").alias("id"), F.col("text").alias("ref"), F.split("text", " ").alias("w"))
        one = w.withColumn("w", F.transform("w", perturb(name, rate, new))).select(F.lit(name).alias("system"), "id", "ref", F.array_join(F.array_compact("w"), " ").alias("hyp"))
        out = one if out is None else out.unionByName(one)
    return out


_SQL_BLEU = f"""(WITH p AS MATERIALIZED {_SQL_HYPS}, n AS (SELECT unnest([1, 2, 3, 4]) AS n),
  h AS (SELECT system, id, n, g, count(*) AS c FROM (SELECT system, id, n, unnest(list_transform(range(1, len(w) - n + 2), lambda i: array_to_string(w[i:i+n-1], ' '))) AS g FROM (SELECT system, id, string_split(hyp, ' ') AS w FROM p), n) GROUP BY ALL),
  r AS (SELECT system, id, n, g, count(*) AS c FROM (SELECT system, id, n, unnest(list_transform(range(1, len(w) - n + 2), lambda i: array_to_string(w[i:i+n-1], ' '))) AS g FROM (SELECT system, id, string_split(ref, ' ') AS w FROM p), n) GROUP BY ALL),
  m AS (SELECT system, n, sum(least(h.c, coalesce(r.c, 0))) AS hit, sum(h.c) AS a FROM h LEFT JOIN r USING (system, id, n, g) GROUP BY ALL),
  g AS (SELECT system, exp(avg(ln(hit / a::DOUBLE))) AS gm FROM m WHERE hit > 0 GROUP BY system HAVING count(*) = 4),
  l AS (SELECT system, sum(len(string_split(hyp, ' '))) AS h, sum(len(string_split(ref, ' '))) AS r FROM p GROUP BY system)
  SELECT system, round(100 * CASE WHEN h >= r THEN 1.0::DOUBLE ELSE exp(1 - r / h::DOUBLE) END * gm, 4) AS bleu FROM g JOIN l USING (system))"""


@query("corpus_bleu", f"SELECT * FROM {_SQL_BLEU}")
@query("mt_systems_bleu", f"SELECT * FROM {_SQL_BLEU}")
def _bleu(spark, d):
    return bleu(hypotheses(table(spark, d, "benchmark")), "system")


@query("system_shortlist", f"SELECT system, rank() OVER (ORDER BY bleu DESC)::INT AS place FROM {_SQL_BLEU} QUALIFY place <= 3")
def shortlist(spark, d, n: int = 3):
    """The best systems by the metric, ties kept; people decide among them. A row for each system is ranked."""
    return _bleu(spark, d).withColumn("place", F.rank().over(Window.orderBy(F.desc("bleu")))).filter(F.col("place") <= n).select("system", "place")


@query("human_best_share", "SELECT event_type, round(count(DISTINCT k)::DOUBLE / (SELECT count(DISTINCT (props->>'$.k')::INT) FROM events), 6) AS share FROM (SELECT event_type, (props->>'$.k')::INT AS k FROM events) GROUP BY event_type")
def human_share(spark, d):
    """Share of items on which a system was chosen; several may be, so shares may exceed one together."""
    e = table(spark, d, "events").select("event_type", F.get_json_object("props", "$.k").cast("int").alias("k"))
    n = e.agg(F.count_distinct("k").alias("all"))
    return e.groupBy("event_type").agg(F.count_distinct("k").alias("c")).join(F.broadcast(n)).select("event_type", F.round(F.col("c") / F.col("all"), 6).alias("share"))


def word_errors(hyp: list[str], ref: list[str]) -> int:
    row = list(range(len(ref) + 1))
    for i, h in enumerate(hyp, 1):
        last, row[0] = row[0], i
        for j, r in enumerate(ref, 1):
            last, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, last + (h != r))
    return row[-1]


@query("wer")
def wer(spark, d):
    """Substitutions, deletions and insertions over the words of the reference, by system."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            pairs = [(h.split(" "), r.split(" ")) for h, r in zip(b.column("hyp").to_pylist(), b.column("ref").to_pylist())]
            yield pa.RecordBatch.from_arrays([b.column("system"), pa.array([word_errors(h, r) for h, r in pairs], pa.int64()), pa.array([len(r) for _, r in pairs], pa.int64())], names=["system", "e", "n"])

    e = hypotheses(table(spark, d, "benchmark")).select("system", "hyp", "ref").mapInArrow(run, "system string, e long, n long")
    return e.groupBy("system").agg(ratio(F.sum("e"), F.sum("n")).alias("wer"))


@query("cer_levenshtein", f"SELECT system, {sql_ratio("sum(levenshtein(regexp_replace(hyp, '[^ -~]', '?', 'g'), regexp_replace(ref, '[^ -~]', '?', 'g')))", 'sum(length(ref))')} AS cer FROM {_SQL_HYPS} GROUP BY system")
def cer(spark, d):
    """Character error rate; letters beyond ASCII count as one sign, because engines differ in what they edit."""
    plain = lambda c: F.regexp_replace(c, "[^ -~]", "?")
    return hypotheses(table(spark, d, "benchmark")).groupBy("system").agg(ratio(F.sum(F.levenshtein(plain("hyp"), plain("ref"))), F.sum(F.length("ref"))).alias("cer"))


#: Scores of models by benchmark: the share of good labels of a source's documents in a language; none where no label is.
_SQL_SCORES = f"(SELECT source AS model, lang AS bench, CASE WHEN count(quality) > 0 THEN {sql_ratio('sum(quality)', 'count(quality)')} END AS score FROM documents LEFT JOIN labels USING (doc_id) GROUP BY ALL)"


def scores(spark, d) -> DataFrame:
    """model, bench, score (null where nothing is labelled)."""
    rated = table(spark, d, "documents").select("doc_id", "source", "lang").join(table(spark, d, "labels").select("doc_id", "quality"), "doc_id", "left")
    score = F.when(F.count("quality") > 0, ratio(F.sum("quality"), F.count("quality"))).alias("score")
    return rated.groupBy(F.col("source").alias("model"), F.col("lang").alias("bench")).agg(score)


@query("mean_ignore_null", f"SELECT model, round(avg(score), 4) AS mean, count(score) AS n FROM {_SQL_SCORES} GROUP BY model")
def mean_ignore_null(spark, d):
    """A model's mean over the benchmarks that have a score of it."""
    return scores(spark, d).groupBy("model").agg(F.round(F.avg("score"), 4).alias("mean"), F.count("score").alias("n"))


@query("leaderboard_rank", f"SELECT bench, model, score, dense_rank() OVER (PARTITION BY bench ORDER BY score DESC)::INT AS place FROM {_SQL_SCORES} WHERE score IS NOT NULL")
def leaderboard(spark, d):
    t = scores(spark, d).filter("score is not null")
    return t.withColumn("place", F.dense_rank().over(Window.partitionBy("bench").orderBy(F.desc("score")))).select("bench", "model", "score", "place")


@query("metric_track", "SELECT day, n, round(avg(n) OVER (ORDER BY day ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 4) AS smooth, n - lag(n) OVER (ORDER BY day) AS change FROM (SELECT ts::DATE AS day, count(*) AS n FROM events GROUP BY 1)")
def track(spark, d):
    """A metric over checkpoints (days): moving mean and change. The series is one row per checkpoint."""
    w = Window.orderBy("day")
    g = table(spark, d, "events").groupBy(F.to_date("ts").alias("day")).agg(F.count("*").alias("n"))
    return g.select("day", "n", F.round(F.avg("n").over(w.rowsBetween(-2, 0)), 4).alias("smooth"), (F.col("n") - F.lag("n").over(w)).alias("change"))


@query("template_questions", "SELECT n_nationkey, 'Which region holds ' || n_name || '?' AS question, r_name AS answer FROM nation JOIN region ON n_regionkey = r_regionkey")
def template_questions(spark, d):
    return table(spark, d, "nation").join(table(spark, d, "region"), F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", F.format_string("Which region holds %s?", "n_name").alias("question"), F.col("r_name").alias("answer"))
