"""Composition, mixtures, curriculum, packing, schedules."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..catalog import query, table
from ..functions.text import SQL_WORDS, ratio, sql_ratio, words
from ..plans.prefixsum import prefix_sum

#: Domain of a language; target : English : code in percent by phase.
DOMAIN = {"en": "english", "fr": "target", "es": "target", "de": "code"}
PRESETS = {"early_epochs": (40, 50, 10), "late_epochs": (50, 40, 10), "continual": (45, 45, 10), "ablation_70_20": (70, 20, 10), "ablation_30_60": (30, 60, 10)}
CONTEXT, BATCH = 4096, 1344
_SQL_DOMAIN = "CASE lang WHEN 'en' THEN 'english' WHEN 'fr' THEN 'target' WHEN 'es' THEN 'target' WHEN 'de' THEN 'code' END"
_SQL_TOKENS = f"(SELECT doc_id, lang, source, {_SQL_DOMAIN} AS domain, len({SQL_WORDS})::BIGINT AS tokens FROM documents)"


def with_tokens(docs: DataFrame) -> DataFrame:
    domain = F.create_map(*[F.lit(x) for kv in DOMAIN.items() for x in kv])[F.col("lang")]
    return docs.select("doc_id", "lang", "source", domain.alias("domain"), F.size(words("text")).cast("bigint").alias("tokens"))


@query("composition_rollup", f"SELECT domain, source, sum(tokens)::BIGINT AS tokens, round(sum(tokens) / (SELECT sum(tokens) FROM {_SQL_TOKENS})::DOUBLE, 6) AS share FROM {_SQL_TOKENS} GROUP BY ROLLUP (domain, source)")
def composition(spark, d):
    """Tokens by domain and source with subtotals; the total is the rollup's own last row."""
    r = with_tokens(table(spark, d, "documents")).rollup("domain", "source").agg(F.sum("tokens").alias("tokens"))
    return r.withColumn("share", F.round(F.col("tokens") / F.max("tokens").over(Window.partitionBy()), 6))


@query("language_share", "SELECT lang, count(*) AS n, round(count(*)::DOUBLE / (SELECT count(*) FROM documents), 6) AS share FROM documents GROUP BY lang")
def language_share(spark, d):
    g = table(spark, d, "documents").groupBy("lang").agg(F.count("*").alias("n"))
    return g.withColumn("share", F.round(F.col("n") / F.sum("n").over(Window.partitionBy()), 6))


def sample(docs: DataFrame, ratios: tuple[int, int, int], budget: int, seed: str = "mix") -> DataFrame:
    """Documents in the order of a seeded hash until each domain's share of the budget is full.

    The running sum of a domain goes through prefix_sum, so no domain passes through one task."""
    target, english, code = ratios
    quota = F.create_map(F.lit("target"), F.lit(budget * target / 100), F.lit("english"), F.lit(budget * english / 100), F.lit("code"), F.lit(budget * code / 100))
    rows = with_tokens(docs).filter("domain is not null").withColumn("order", F.md5(F.concat(F.lit(seed), F.col("doc_id").cast("string")).cast("binary")))
    ran = prefix_sum(rows, ["domain", "order", "doc_id"], F.col("tokens"), "before")
    first = ran.groupBy("domain").agg(F.min("before").alias("at"))
    return ran.join(first, "domain").withColumn("before", F.col("before") - F.col("at")).filter(F.col("before") + F.col("tokens") <= quota[F.col("domain")]).select("doc_id", "domain", "tokens")


def sql_sample(ratios: tuple[int, int, int], budget: str, seed: str = "mix") -> str:
    t, e, c = ratios
    return f"""SELECT doc_id, domain, tokens FROM (SELECT *, sum(tokens) OVER (PARTITION BY domain ORDER BY md5('{seed}' || doc_id::VARCHAR), doc_id) AS upto FROM {_SQL_TOKENS} WHERE domain IS NOT NULL)
    WHERE upto <= {budget} * CASE domain WHEN 'target' THEN {t} WHEN 'english' THEN {e} ELSE {c} END / 100.0"""


@query("mixture_sample", sql_sample(PRESETS["early_epochs"], "100000"))
def _sample(spark, d):
    return sample(table(spark, d, "documents"), PRESETS["early_epochs"], 100_000)


@query("mixture_presets", " UNION ALL ".join(f"SELECT '{n}' AS preset, domain, count(*) AS n, sum(tokens)::BIGINT AS tokens FROM ({sql_sample(r, '60000')}) GROUP BY domain" for n, r in PRESETS.items()))
def _presets(spark, d):
    out = None
    for n, r in PRESETS.items():
        one = sample(table(spark, d, "documents"), r, 60_000).groupBy("domain").agg(F.count("*").alias("n"), F.sum("tokens").alias("tokens")).withColumn("preset", F.lit(n))
        out = one if out is None else out.unionByName(one)
    return out


@query("mixture_repeat", f"WITH t AS {_SQL_TOKENS}, s AS (SELECT domain, least(4, greatest(1, ceil(400000.0 / sum(tokens))))::INT AS k FROM t WHERE domain IS NOT NULL GROUP BY domain) SELECT doc_id, unnest(range(1, k + 1))::INT AS epoch FROM t JOIN s USING (domain)")
def repeat(spark, d, budget: int = 400_000, most: int = 4):
    """Domains short of their budget are repeated, four epochs at most."""
    t = with_tokens(table(spark, d, "documents")).filter("domain is not null")
    k = t.groupBy("domain").agg(F.least(F.lit(most), F.greatest(F.lit(1), F.ceil(F.lit(float(budget)) / F.sum("tokens")))).cast("int").alias("k"))
    return t.join(k, "domain").select("doc_id", F.explode(F.sequence(F.lit(1), F.col("k"))).alias("epoch"))


#: phase -> (epochs, least unique-word share, share of documents kept by quality order)
PHASES = (("broad", (1, 2), 0.0), ("educated", (3, 4), 0.5), ("cooldown", (5,), 0.8))
_SQL_UNIQUE = f"(SELECT doc_id, CASE WHEN len(w) > 0 THEN len(list_distinct(w))::DOUBLE / len(w) ELSE 0 END AS u, len(w)::BIGINT AS tokens FROM (SELECT doc_id, {SQL_WORDS} AS w FROM documents))"


@query("curriculum_plan", " UNION ALL ".join(f"SELECT '{p}' AS phase, {e} AS epoch, count(*) AS n, sum(tokens)::BIGINT AS tokens FROM {_SQL_UNIQUE} WHERE u >= {u}" for p, es, u in PHASES for e in es))
def curriculum(spark, d):
    """Documents and tokens of each epoch: later phases take what passes stricter filters. One scan serves all phases."""
    w = table(spark, d, "documents").select("doc_id", words("text").alias("w"))
    rows = w.select("doc_id", F.when(F.size("w") > 0, F.size(F.array_distinct("w")) / F.size("w")).otherwise(0.0).alias("u"), F.size("w").cast("bigint").alias("tokens"))
    plan = spark.createDataFrame([(p, e, u) for p, es, u in PHASES for e in es], "phase string, epoch int, least double")
    return rows.join(F.broadcast(plan), F.col("u") >= F.col("least")).groupBy("phase", "epoch").agg(F.count("*").alias("n"), F.sum("tokens").alias("tokens"))


@query("cooldown_subset", f"SELECT doc_id FROM (SELECT doc_id, sum(tokens) OVER (ORDER BY -round(u, 6), doc_id) AS upto FROM {_SQL_UNIQUE}) WHERE upto <= 50000")
def cooldown(spark, d, budget: int = 50_000):
    """The best documents until the budget is full, best first, by a running sum over ranges."""
    w = table(spark, d, "documents").select("doc_id", words("text").alias("w"))
    rows = w.select("doc_id", (-F.round(F.when(F.size("w") > 0, F.size(F.array_distinct("w")) / F.size("w")).otherwise(0.0), 6)).alias("worse"), F.size("w").cast("bigint").alias("tokens"))
    return prefix_sum(rows, ["worse", "doc_id"], F.col("tokens"), "before").filter(F.col("before") + F.col("tokens") <= budget).select("doc_id")


def pack(docs: DataFrame, context: int = CONTEXT) -> DataFrame:
    """(seq_id, doc_id, from_tok, to_tok): documents laid end to end and cut at every `context` tokens."""
    rows = prefix_sum(with_tokens(docs).filter("tokens > 0").select("doc_id", "tokens"), ["doc_id"], F.col("tokens"), "start")
    first, last = F.floor(F.col("start") / context), F.floor((F.col("start") + F.col("tokens") - 1) / context)
    each = rows.withColumn("seq_id", F.explode(F.sequence(first, last)))
    return each.select("seq_id", "doc_id", F.greatest(F.lit(0), F.col("seq_id") * context - F.col("start")).alias("from_tok"), F.least("tokens", (F.col("seq_id") + 1) * context - F.col("start")).alias("to_tok"))


_SQL_PACK = f"""(SELECT seq_id, doc_id, greatest(0, seq_id * 4096 - start)::BIGINT AS from_tok, least(tokens, (seq_id + 1) * 4096 - start)::BIGINT AS to_tok FROM
  (SELECT *, unnest(range((start // 4096)::BIGINT, ((start + tokens - 1) // 4096 + 1)::BIGINT)) AS seq_id FROM
   (SELECT doc_id, tokens, (sum(tokens) OVER (ORDER BY doc_id) - tokens)::BIGINT AS start FROM {_SQL_TOKENS} WHERE tokens > 0)))"""


@query("packed_sequences", f"SELECT * FROM {_SQL_PACK}")
def _pack(spark, d):
    return pack(table(spark, d, "documents"))


@query("batch_stats", f"SELECT seq_id // 16 AS batch_id, count(DISTINCT seq_id) AS n_seq, sum(to_tok - from_tok)::BIGINT AS tokens, count(DISTINCT doc_id) AS n_docs FROM {_SQL_PACK} GROUP BY 1")
def batches(spark, d, size: int = 16):
    return pack(table(spark, d, "documents")).groupBy(F.floor(F.col("seq_id") / size).alias("batch_id")).agg(F.count_distinct("seq_id").alias("n_seq"), F.sum(F.col("to_tok") - F.col("from_tok")).alias("tokens"), F.count_distinct("doc_id").alias("n_docs"))


@query("batch_backtrace", f"SELECT DISTINCT doc_id, md5(text) AS digest FROM {_SQL_PACK} JOIN documents USING (doc_id) WHERE seq_id // 16 = 1")
def trace(spark, d):
    """Texts behind one batch: a semi join on the few ids of its sequences."""
    docs = table(spark, d, "documents")
    return docs.join(pack(docs).filter(F.floor(F.col("seq_id") / 16) == 1).select("doc_id").distinct(), "doc_id", "left_semi").select("doc_id", F.md5("text").alias("digest"))


@query("lr_schedule", "WITH s AS MATERIALIZED (SELECT DISTINCT doc_id // 16 AS s FROM documents WHERE doc_id IS NOT NULL), e AS (SELECT max(s) + 1 AS n FROM s) SELECT s AS step, round(CASE WHEN 10 * s < n THEN 3e-4 * (10 * s) / n WHEN 10 * s < 9 * n THEN 3e-5 + 0.5 * (3e-4 - 3e-5) * (1 + cos(pi() * (10 * s - n) / (8 * n))) ELSE 3e-5 * (10 * (n - s)) / n END, 9)::DOUBLE AS lr FROM s, e")
def lr_schedule(spark, d, size=16, peak=3e-4, least=3e-5):
    """The rate of each step, a batch of `size` documents in order of their ids: linear warm-up over a tenth of the steps,
    cosine to the least rate until the last tenth, linear to zero."""
    steps = table(spark, d, "documents").filter("doc_id is not null").select(F.floor(F.col("doc_id") / size).alias("s")).distinct()
    s, n = F.col("s"), F.col("n")
    lr = F.when(10 * s < n, F.lit(peak) * (10 * s) / n).when(10 * s < 9 * n, least + 0.5 * (peak - least) * (1 + F.cos(F.lit(3.141592653589793) * (10 * s - n) / (8 * n)))).otherwise(F.lit(least) * (10 * (n - s)) / n)
    return steps.crossJoin(F.broadcast(steps.agg((F.max("s") + 1).alias("n")))).select(s.alias("step"), F.round(lr, 9).alias("lr"))


@query("license_lines", r"SELECT doc_id, len(list_filter(string_split(text, chr(10)), lambda x: regexp_matches(x, '(?i)licen[cs]e|copyright')))::INT AS n FROM documents WHERE regexp_matches(text, '(?i)licen[cs]e|copyright')")
def license_lines(spark, d):
    p = "(?i)licen[cs]e|copyright"
    return table(spark, d, "documents").filter(F.col("text").rlike(p)).select("doc_id", F.size(F.filter(F.split("text", "\n"), lambda x: x.rlike(p))).alias("n"))
