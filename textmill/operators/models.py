"""Semantic filters, n-gram language models with perplexity, education scores, language identification, privacy."""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..catalog import query, table
from ..functions.text import SQL_WORDS, h28, ratio, sql_h28, sql_ratio, words, words_of
from ..plans.components import reliable
from ..plans.ranks import quantiles
from ..plans.spread import spread
from .clean import SQL_HOST, host
from .quality import sql_signals, signals

_SQL_WORD_DOCS = f"(SELECT doc_id, unnest(list_distinct({SQL_WORDS})) AS word FROM documents)"


def induce_lexicon(docs: DataFrame, labels: DataFrame, min_df: int = 3, lift: float = 4.0) -> DataFrame:
    """(word, n, n_toxic): words of min_df labelled documents or more whose toxic share is `lift` times the base share."""
    lab = labels.select("doc_id", "toxic")
    base = lab.agg(F.avg("toxic").alias("base"))
    each = spread(docs.select("doc_id", "text")).join(lab, "doc_id").select("doc_id", "toxic", F.explode(F.array_distinct(words("text"))).alias("word"))
    g = each.groupBy("word").agg(F.count("*").alias("n"), F.sum("toxic").cast("bigint").alias("n_toxic")).filter(F.col("n") >= min_df)
    return g.join(F.broadcast(base), F.col("n_toxic") >= F.col("n") * F.col("base") * lift).select("word", "n", "n_toxic")


_SQL_LEXICON = f"SELECT word, count(*) AS n, sum(toxic)::BIGINT AS n_toxic FROM {_SQL_WORD_DOCS} JOIN labels USING (doc_id) GROUP BY word HAVING count(*) >= 3 AND sum(toxic) >= count(*) * (SELECT avg(toxic) FROM labels) * 4.0"


@query("toxic_lexicon_induced", _SQL_LEXICON)
def _lexicon(spark, d):
    return induce_lexicon(table(spark, d, "documents"), table(spark, d, "labels"))


def flag(docs: DataFrame, lexicon: DataFrame) -> DataFrame:
    """(doc_id, hits) of documents with a word of the lexicon; Spark broadcasts the lexicon if it is small."""
    each = spread(docs.select("doc_id", "text")).select("doc_id", F.explode(F.array_distinct(words("text"))).alias("word"))
    return each.join(lexicon.select("word"), "word", "left_semi").groupBy("doc_id").agg(F.count("*").alias("hits"))


_SQL_FLAG = f"SELECT doc_id, count(*) AS hits FROM {_SQL_WORD_DOCS} SEMI JOIN ({_SQL_LEXICON}) USING (word) GROUP BY doc_id"


@query("toxic_lexicon", _SQL_FLAG)
def _flag(spark, d):
    docs = table(spark, d, "documents")
    return flag(docs, induce_lexicon(docs, table(spark, d, "labels")))


@query("toxic_metrics", f"SELECT tp, fp, fn, {sql_ratio('tp', '(tp + fp)')} AS precision, {sql_ratio('tp', '(tp + fn)')} AS recall FROM (SELECT sum((f.hits IS NOT NULL AND toxic = 1)::INT)::BIGINT AS tp, sum((f.hits IS NOT NULL AND toxic = 0)::INT)::BIGINT AS fp, sum((f.hits IS NULL AND toxic = 1)::INT)::BIGINT AS fn FROM labels LEFT JOIN ({_SQL_FLAG}) f USING (doc_id))")
def _toxic_metrics(spark, d):
    j = table(spark, d, "labels").join(_flag(spark, d), "doc_id", "left")
    hit, t = F.col("hits").isNotNull(), F.col("toxic")
    s = j.agg(F.count_if(hit & (t == 1)).alias("tp"), F.count_if(hit & (t == 0)).alias("fp"), F.count_if(~hit & (t == 1)).alias("fn"))
    return s.select("*", ratio(F.col("tp"), F.col("tp") + F.col("fp")).alias("precision"), ratio(F.col("tp"), F.col("tp") + F.col("fn")).alias("recall"))


@query("domain_audit_sample", f"WITH p AS (SELECT page_id, {SQL_HOST} AS host FROM pages), t AS (SELECT host, count(*) AS n FROM p GROUP BY host ORDER BY n DESC, host LIMIT 10) SELECT host, page_id FROM p JOIN t USING (host) QUALIFY row_number() OVER (PARTITION BY host ORDER BY md5(page_id::VARCHAR), page_id) <= 20")
def domain_sample(spark, d, top: int = 10, k: int = 20):
    """20 pages of each of the commonest domains, in hash order."""
    p = table(spark, d, "pages").select("page_id", host(F.col("url")).alias("host"))
    t = p.groupBy("host").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "host").limit(top)
    rn = F.row_number().over(Window.partitionBy("host").orderBy(F.md5(F.col("page_id").cast("string").cast("binary")), "page_id"))
    return p.join(t, "host").withColumn("rn", rn).filter(F.col("rn") <= k).select("host", "page_id")


@query("domain_scores", "SELECT source AS domain, count(*) AS n, round(avg(quality), 6) AS score FROM documents JOIN labels USING (doc_id) GROUP BY source")
def domain_scores(spark, d):
    return table(spark, d, "documents").join(table(spark, d, "labels"), "doc_id").groupBy(F.col("source").alias("domain")).agg(F.count("*").alias("n"), F.round(F.avg("quality"), 6).alias("score"))


# Bigram model with additive smoothing, one per language, trained on good documents with an even hash.
_SQL_TRAIN = f"(SELECT lang, list_prepend('<s>', {SQL_WORDS}) AS w FROM documents JOIN labels USING (doc_id) WHERE quality = 1 AND {sql_h28('doc_id::VARCHAR')} % 2 = 0)"
_SQL_BIGRAMS = f"(SELECT lang, w[i] AS v, w[i + 1] AS w, count(*) AS n FROM (SELECT lang, w, unnest(range(1, len(w))) AS i FROM {_SQL_TRAIN}) GROUP BY ALL)"
ADD = 0.1


def _pairs(df: DataFrame, by_doc: bool) -> DataFrame:
    """(doc_id, lang, v, w, n) or (lang, v, w, n): neighbours, from a line start on, counted in each document, or in each slice
    of a batch; words don't leave the batch one by one."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                part = batch.slice(at, 512)
                counts: Counter = Counter()
                for doc_id, lang, text in zip(*(part.column(c).to_pylist() for c in ("doc_id", "lang", "text"))):
                    w = words_of(text)
                    counts.update((doc_id if by_doc else None, lang, v, x) for v, x in zip(["<s>", *w], w))
                cols = [*zip(*counts)] or [()] * 4
                arrays = [pa.array(c, t) for c, t in zip(cols, (pa.int64(), pa.string(), pa.string(), pa.string()))]
                yield pa.RecordBatch.from_arrays([*arrays, pa.array(counts.values(), pa.int64())], names=["doc_id", "lang", "v", "w", "n"])

    found = spread(df.select(F.col("doc_id").cast("long").alias("doc_id"), "lang", "text")).mapInArrow(run, "doc_id long, lang string, v string, w string, n long")
    return found if by_doc else found.drop("doc_id")


def train_bigrams(docs: DataFrame, labels: DataFrame) -> DataFrame:
    good = docs.join(labels.filter("quality = 1").select("doc_id"), "doc_id", "left_semi").filter(h28(F.col("doc_id").cast("string")) % 2 == 0)
    return _pairs(good, False).groupBy("lang", "v", "w").agg(F.sum("n").alias("n"))


@query("lm_bigram_counts", f"SELECT * FROM {_SQL_BIGRAMS}")
def _bigrams(spark, d):
    return train_bigrams(table(spark, d, "documents"), table(spark, d, "labels"))


def perplexity(docs: DataFrame, bigrams: DataFrame) -> DataFrame:
    """(doc_id, source, n, ppl): exp of minus the mean log probability under the bigrams of the document's language.

    Each document's distinct bigrams are counted before they meet the model, so the join is on types, not tokens; an
    unseen context falls back to the uniform distribution through the additive term."""
    ctx = bigrams.groupBy("lang", "v").agg(F.sum("n").alias("c"))
    vocab = bigrams.groupBy("lang").agg(F.count_distinct("w").alias("size"))
    own = _pairs(docs, True).withColumnRenamed("n", "k")
    j = own.join(bigrams, ["lang", "v", "w"], "left").join(ctx, ["lang", "v"], "left").join(vocab, "lang", "left")
    p = (F.coalesce("n", F.lit(0)) + ADD) / (F.coalesce("c", F.lit(0)) + ADD * (F.coalesce("size", F.lit(0)) + 1))
    g = j.groupBy("doc_id").agg(F.sum("k").alias("n"), F.sum(F.col("k") * F.log(p)).alias("lp"))
    return g.select("doc_id", "n", F.round(F.exp(-F.col("lp") / F.col("n")), 4).alias("ppl"))


_SQL_PPL = f"""(WITH b AS MATERIALIZED (SELECT * FROM {_SQL_BIGRAMS}), c AS (SELECT lang, v, sum(n) AS c FROM b GROUP BY ALL), z AS (SELECT lang, count(DISTINCT w) AS size FROM b GROUP BY ALL),
  t AS (SELECT doc_id, lang, list_prepend('<s>', {SQL_WORDS}) AS w FROM documents), o AS (SELECT doc_id, lang, w[i] AS v, w[i + 1] AS w, count(*) AS k FROM (SELECT doc_id, lang, w, unnest(range(1, len(w))) AS i FROM t) GROUP BY ALL)
  SELECT doc_id, sum(k)::BIGINT AS n, round(exp(-sum(k * ln((coalesce(n, 0) + 0.1::DOUBLE) / (coalesce(c, 0) + 0.1::DOUBLE * (coalesce(size, 0) + 1)))) / sum(k)), 4) AS ppl
  FROM o LEFT JOIN b USING (lang, v, w) LEFT JOIN c USING (lang, v) LEFT JOIN z USING (lang) GROUP BY doc_id)"""


@query("doc_perplexity", f"SELECT * FROM {_SQL_PPL}")
def _ppl(spark, d):
    docs = table(spark, d, "documents")
    return perplexity(docs, train_bigrams(docs, table(spark, d, "labels")))


def drop_by_perplexity(ppl: DataFrame, by: str = "source", high: float | None = 0.95, low: float | None = None) -> DataFrame:
    """Rows not above the high quantile of their dataset, nor below the low one. Quantiles are exact and come from ranks over
    ranges, so a dataset of any size is dealt to many tasks."""
    ppl = reliable(ppl)
    q = quantiles(ppl, by, "ppl", {"hi": high if high is not None else 1.0, "lo": low if low is not None else 0.0})
    return ppl.join(q, by).filter((F.round("ppl", 4) <= F.round("hi", 4)) & (F.round("ppl", 4) >= F.round("lo", 4))).drop("hi", "lo")


for _name, _hi, _lo in (("ppl_high_filter", 0.95, None), ("ppl_low_filter", None, 0.05)):

    def _dropped(spark, d, hi=_hi, lo=_lo):
        return drop_by_perplexity(_ppl(spark, d).join(table(spark, d, "documents").select("doc_id", "source"), "doc_id"), "source", hi, lo).select("doc_id", "source")

    query(_name, f"WITH p AS MATERIALIZED (SELECT doc_id, source, ppl FROM {_SQL_PPL} JOIN documents USING (doc_id)), q AS (SELECT source, quantile_cont(ppl, {_hi or 1.0}) AS hi, quantile_cont(ppl, {_lo or 0.0}) AS lo FROM p GROUP BY source) SELECT doc_id, source FROM p JOIN q USING (source) WHERE ppl <= round(hi, 4) AND ppl >= round(lo, 4)")(_dropped)


@query("ablation_ppl", f"SELECT recipe, count(*) AS n, round(avg(ppl), 3) AS mean_ppl FROM (SELECT 'all' AS recipe, doc_id FROM documents UNION ALL SELECT 'own_rules', doc_id FROM ({sql_signals()}) WHERE n_words >= 10 AND frac_unique_words >= 0.2 AND special_char_frac <= 0.1 UNION ALL SELECT 'fixed_cutoffs', doc_id FROM ({sql_signals()}) WHERE special_char_frac <= 0.2) JOIN {_SQL_PPL} USING (doc_id) GROUP BY recipe")
def ablation_ppl(spark, d):
    """Stand-in for training a model on each recipe: mean perplexity of what it keeps under a model of good text."""
    sig = signals(table(spark, d, "documents"))
    own = (F.col("n_words") >= 10) & (F.col("frac_unique_words") >= 0.2) & (F.col("special_char_frac") <= 0.1)
    r = sig.select("doc_id", F.explode(F.array_compact(F.array(F.lit("all"), F.when(own, F.lit("own_rules")), F.when(F.col("special_char_frac") <= 0.2, F.lit("fixed_cutoffs"))))).alias("recipe"))
    return r.join(_ppl(spark, d), "doc_id").groupBy("recipe").agg(F.count("*").alias("n"), F.round(F.avg("ppl"), 3).alias("mean_ppl"))


def rubric(sig: DataFrame) -> DataFrame:
    """Education score 0-5: a point each for varied words, few special characters, ended lines, length and stop words.

    A deterministic stand-in for annotation by a language model."""
    tests = (F.col("frac_unique_words") >= 0.5, F.col("special_char_frac") < 0.05, F.col("frac_lines_terminal") >= 0.5, F.col("n_words") >= 50, F.col("stopword_frac") >= 0.05)
    return sig.select("doc_id", sum((t.cast("int") for t in tests), F.lit(0)).alias("score"))


_SQL_RUBRIC = f"(SELECT doc_id, (frac_unique_words >= 0.5)::INT + (special_char_frac < 0.05)::INT + (frac_lines_terminal >= 0.5)::INT + (n_words >= 50)::INT + (stopword_frac >= 0.05)::INT AS score FROM ({sql_signals()}))"


@query("edu_annotate_rubric", f"SELECT * FROM {_SQL_RUBRIC}")
def _rubric(spark, d):
    return rubric(signals(table(spark, d, "documents")))


@query("edu_filter", f"SELECT doc_id FROM {_SQL_RUBRIC} WHERE score NOT IN (0, 1)")
def _edu_filter(spark, d):
    return _rubric(spark, d).filter("score not in (0, 1)").select("doc_id")


@query("edu_scores")
def edu_scores(spark, d):
    """A regression head on numeric features of the text, fitted to the rubric of a hash sample, then rounded and clipped."""
    from pyspark.ml.feature import VectorAssembler
    from pyspark.ml.regression import LinearRegression

    names = ["n_words", "frac_unique_words", "special_char_frac", "frac_lines_terminal", "stopword_frac", "mean_word_len", "digit_frac"]
    sig = signals(table(spark, d, "documents"))
    rows = VectorAssembler(inputCols=names, outputCol="x").transform(sig.join(rubric(sig), "doc_id"))
    model = LinearRegression(featuresCol="x", labelCol="score", regParam=0.01).fit(rows.filter(h28(F.col("doc_id").cast("string")) % 2 == 0))
    return model.transform(rows).select("doc_id", F.greatest(F.lit(0), F.least(F.lit(5), F.round("prediction"))).cast("int").alias("score"), F.col("score").alias("rubric"))


_SQL_CENTROID = "(SELECT label, list(m ORDER BY i) AS c FROM (SELECT label, i, avg(embedding[i]::DOUBLE) AS m FROM embeddings, (SELECT unnest(range(1, 65)) AS i) WHERE vec_id % 2 = 0 GROUP BY ALL) GROUP BY label)"
_SQL_CLASSIFY = f"(SELECT vec_id, e.label AS gold, arg_max(k.label, (round(list_dot_product(e.embedding::DOUBLE[], k.c), 6), -k.label)) AS pred FROM embeddings e, {_SQL_CENTROID} k WHERE vec_id % 2 = 1 GROUP BY ALL)"


def centroids(emb: DataFrame) -> DataFrame:
    m = emb.select("label", F.posexplode("embedding").alias("i", "v")).groupBy("label", "i").agg(F.avg(F.col("v").cast("double")).alias("m"))
    return m.groupBy("label").agg(F.transform(F.array_sort(F.collect_list(F.struct("i", "m"))), lambda x: x["m"]).alias("c"))


@query("centroid_classify", f"SELECT * FROM {_SQL_CLASSIFY}")
def centroid_classify(spark, d):
    """Nearest centroid of even vectors for odd ones; the centroids are one row per class."""
    e = table(spark, d, "embeddings")
    k = centroids(e.filter("vec_id % 2 = 0")).withColumnRenamed("label", "k")
    dot = F.round(F.aggregate(F.zip_with("embedding", "c", lambda a, b: a.cast("double") * b), F.lit(0.0), lambda s, x: s + x), 6)
    return e.filter("vec_id % 2 = 1").crossJoin(F.broadcast(k)).groupBy("vec_id", F.col("label").alias("gold")).agg(F.max_by("k", F.struct(dot, -F.col("k"))).alias("pred"))


@query("classifier_confusion", f"SELECT gold, pred, count(*) AS n FROM {_SQL_CLASSIFY} GROUP BY ALL")
def _confusion(spark, d):
    return centroid_classify(spark, d).groupBy("gold", "pred").agg(F.count("*").alias("n"))


_SQL_STOP = f"(SELECT lang AS l, word FROM (SELECT lang, word, count(*) AS n FROM (SELECT lang, unnest({SQL_WORDS}) AS word FROM documents) GROUP BY ALL) QUALIFY row_number() OVER (PARTITION BY lang ORDER BY n DESC, word) <= 20)"
_ORDER = {"en": 0, "es": 1, "fr": 2, "de": 3}


@query("language_id", f"WITH s AS MATERIALIZED {_SQL_STOP}, h AS (SELECT doc_id, l, count(*) AS hits FROM (SELECT doc_id, unnest({SQL_WORDS}) AS word FROM documents) JOIN s USING (word) GROUP BY ALL), b AS (SELECT doc_id, arg_max(l, (hits, -CASE l WHEN 'en' THEN 0 WHEN 'es' THEN 1 WHEN 'fr' THEN 2 ELSE 3 END)) AS pred FROM h GROUP BY doc_id) SELECT lang, coalesce(pred, 'und') AS pred, count(*) AS n FROM documents LEFT JOIN b USING (doc_id) GROUP BY ALL")
def language_id(spark, d):
    """The language whose 20 commonest words a document has most of, against its label."""
    docs = table(spark, d, "documents")
    each = docs.select("doc_id", "lang", F.explode(words("text")).alias("word"))
    n = each.groupBy("lang", "word").agg(F.count("*").alias("n"))
    stop = n.withColumn("rn", F.row_number().over(Window.partitionBy("lang").orderBy(F.desc("n"), "word"))).filter("rn <= 20").select(F.col("lang").alias("l"), "word")
    hits = each.select("doc_id", "word").join(stop, "word").groupBy("doc_id", "l").agg(F.count("*").alias("hits"))
    order = F.create_map(*[F.lit(x) for kv in _ORDER.items() for x in kv])[F.col("l")]
    best = hits.groupBy("doc_id").agg(F.max_by("l", F.struct("hits", -order)).alias("pred"))
    return docs.join(best, "doc_id", "left").groupBy("lang", F.coalesce("pred", F.lit("und")).alias("pred")).agg(F.count("*").alias("n"))


EMAIL, PHONE = r"[A-Za-z0-9._%+-]+@[A-Za-z0-9.-]+\.[A-Za-z]{2,}", r"[+]?[0-9][0-9 ()-]{7,}[0-9]"


def masked(text: Column) -> Column:
    return F.regexp_replace(F.regexp_replace(text, EMAIL, "<EMAIL>"), PHONE, "<PHONE>")


@query("pii_mask", f"SELECT doc_id, regexp_replace(regexp_replace(text, '{EMAIL}', '<EMAIL>', 'g'), '{PHONE}', '<PHONE>', 'g') AS text FROM documents WHERE regexp_matches(text, '{EMAIL}') OR regexp_matches(text, '{PHONE}')")
def _pii(spark, d):
    return table(spark, d, "documents").filter(F.col("text").rlike(EMAIL) | F.col("text").rlike(PHONE)).select("doc_id", masked(F.col("text")).alias("text"))


@query("benchmark_overlap", f"WITH g AS (SELECT doc_id, unnest(list_transform(range(1, len(w) - 6), lambda i: array_to_string(w[i:i+7], ' '))) AS g FROM (SELECT doc_id, {SQL_WORDS} AS w FROM documents) WHERE len(w) >= 8), b AS (SELECT item_id, unnest(list_transform(range(1, len(w) - 6), lambda i: array_to_string(w[i:i+7], ' '))) AS g FROM (SELECT item_id, {SQL_WORDS} AS w FROM benchmark) WHERE len(w) >= 8) SELECT doc_id, count(DISTINCT item_id) AS n_items FROM g JOIN b USING (g) GROUP BY doc_id")
def benchmark_overlap(spark, d):
    """Documents that share an 8-gram of words with a benchmark item; grams are hashed where they are cut."""
    from .dedup import shingled

    a = shingled(table(spark, d, "documents").filter(F.size(words("text")) >= 8)).select("doc_id", F.explode("s").alias("g"))
    b = shingled(table(spark, d, "benchmark").filter(F.size(words("text")) >= 8).select(F.col("item_id").alias("doc_id"), "text")).select(F.col("doc_id").alias("item_id"), F.explode("s").alias("g"))
    return a.join(b, "g").groupBy("doc_id").agg(F.count_distinct("item_id").alias("n_items"))
