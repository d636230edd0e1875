"""Further measures and workloads: alignment by tokenizer, approximate search, curation, preference balance, prompts."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..catalog import ORACLE, query, table
from ..functions.text import SQL_WORDS, h28, ratio, sql_h28, sql_ratio, words
from ..plans.ranks import cut_points, ranked
from ..plans.spread import spread
from . import dedup, evaluation, models, post, retrieval, tokenizer


@query("alignment_by_tokenizer")
def alignment_by_tokenizer(spark, d):
    return tokenizer.tokenizer_comparison(spark, d).select("tokenizer", "alignment", "boundary_f1")


_SQL_IVF = "(SELECT label, list(m ORDER BY i) AS c FROM (SELECT label, i, round(avg(embedding[i]::DOUBLE), 6) AS m FROM embeddings, (SELECT unnest(range(1, 65)) AS i) GROUP BY ALL) GROUP BY label)"
_SQL_IVF_TOP = f"(WITH p AS (SELECT vec_id AS qid, embedding AS q, k.label FROM embeddings, {_SQL_IVF} k WHERE {retrieval.ASKED} QUALIFY row_number() OVER (PARTITION BY vec_id ORDER BY round(list_dot_product(embedding::DOUBLE[], k.c), 5) DESC, k.label) <= 5) SELECT qid, vec_id AS cid FROM p JOIN embeddings e USING (label) WHERE qid <> vec_id QUALIFY row_number() OVER (PARTITION BY qid ORDER BY round(list_dot_product(q::DOUBLE[], embedding::DOUBLE[]), 6) DESC, vec_id) <= 20)"


def ivf(spark, d, probes: int = 5, k: int = 20) -> DataFrame:
    """Search in the `probes` nearest lists only; a list is the vectors of one centroid (here: one label)."""
    e = table(spark, d, "embeddings")
    c = retrieval.weight_average(spark, d)
    near = F.round(dedup.cosine(F.col("q"), F.col("v")), 5)
    q = e.filter(retrieval.ASKED).select(F.col("vec_id").alias("qid"), F.col("embedding").alias("q"))
    p = q.crossJoin(F.broadcast(c)).withColumn("rn", F.row_number().over(Window.partitionBy("qid").orderBy(F.desc(near), "label"))).filter(F.col("rn") <= probes).select("qid", "q", "label")
    j = p.join(e.select(F.col("vec_id").alias("cid"), "embedding", "label"), "label").filter("qid <> cid")
    sim = F.round(dedup.cosine(F.col("q"), F.col("embedding")), 6)
    return j.withColumn("rn", F.row_number().over(Window.partitionBy("qid").orderBy(F.desc(sim), "cid"))).filter(F.col("rn") <= k).select("qid", "cid")


@query("ivf_topk", f"SELECT * FROM {_SQL_IVF_TOP}")
def _ivf(spark, d):
    return ivf(spark, d)


_SQL_EXACT = f"(SELECT q.vec_id AS qid, c.vec_id AS cid FROM embeddings q JOIN embeddings c ON q.vec_id <> c.vec_id WHERE q.{retrieval.ASKED} QUALIFY row_number() OVER (PARTITION BY q.vec_id ORDER BY round(list_dot_product(q.embedding::DOUBLE[], c.embedding::DOUBLE[]), 6) DESC, c.vec_id) <= 20)"


@query("ann_recall", f"SELECT count(*) AS n, {sql_ratio('(SELECT count(*) FROM ' + _SQL_EXACT + ' SEMI JOIN ' + _SQL_IVF_TOP + ' USING (qid, cid))', 'count(*)')} AS recall FROM {_SQL_EXACT}")
def ann_recall(spark, d):
    e = table(spark, d, "embeddings")
    exact = retrieval.search(e.filter(retrieval.ASKED), e, least=-2.0).select("qid", "cid")
    found = ivf(spark, d).select("qid", "cid", F.lit(1).alias("f"))
    return exact.join(found, ["qid", "cid"], "left").agg(F.count("*").alias("n"), ratio(F.count("f"), F.count("*")).alias("recall"))


@query("attribution_scores", f"SELECT count(*) AS n, {sql_ratio('count(*) FILTER (support >= 0.5)', 'count(*)')} AS support_rate, round(avg(support), 6) AS mean_support FROM ({ORACLE['attribute_sentences']})")
def attribution_scores(spark, d):
    """Share of sentences with evidence, and their mean support."""
    return retrieval.attribute(spark, d).agg(F.count("*").alias("n"), ratio(F.count_if(F.col("support") >= 0.5), F.count("*")).alias("support_rate"), F.round(F.avg("support"), 6).alias("mean_support"))


@query("benchmark_curation", f"SELECT item_id FROM benchmark WHERE len({SQL_WORDS}) >= 20 AND item_id IN (SELECT min(item_id) FROM benchmark GROUP BY array_to_string(({SQL_WORDS})[1:3], ' '))")
def curation(spark, d):
    """Items long enough, one of each opening."""
    b = table(spark, d, "benchmark").select("item_id", words("text").alias("w"))
    first = b.groupBy(F.array_join(F.slice("w", 1, 3), " ").alias("o")).agg(F.min("item_id").alias("item_id"))
    return b.filter(F.size("w") >= 20).join(first.select("item_id"), "item_id", "left_semi").select("item_id")


@query("best10_average", "WITH c AS (SELECT label AS l, list(m ORDER BY i) AS c FROM (SELECT label, i, round(avg(embedding[i]::DOUBLE), 6) AS m FROM embeddings, (SELECT unnest(range(1, 65)) AS i) GROUP BY ALL) GROUP BY label), t AS (SELECT label, embedding FROM embeddings JOIN c ON l = label QUALIFY row_number() OVER (PARTITION BY label ORDER BY round(list_dot_product(embedding::DOUBLE[], c), 6) DESC, vec_id) <= 10) SELECT label, list(m ORDER BY i) AS v FROM (SELECT label, i, round(avg(embedding[i]::DOUBLE), 5) AS m FROM t, (SELECT unnest(range(1, 65)) AS i) GROUP BY ALL) GROUP BY label")
def best10(spark, d, k: int = 10):
    """The ten vectors of a group that do best by a validation score (cosine to the centroid) are averaged."""
    e = table(spark, d, "embeddings").join(F.broadcast(retrieval.weight_average(spark, d).withColumnRenamed("v", "c")), "label")
    s = F.round(dedup.cosine(F.col("embedding"), F.col("c")), 6)
    top = e.withColumn("rn", F.row_number().over(Window.partitionBy("label").orderBy(F.desc(s), "vec_id"))).filter(F.col("rn") <= k)
    m = top.select("label", F.posexplode("embedding").alias("i", "x")).groupBy("label", "i").agg(F.round(F.avg(F.col("x").cast("double")), 5).alias("m"))
    return m.groupBy("label").agg(F.transform(F.array_sort(F.collect_list(F.struct("i", "m"))), lambda x: x["m"]).alias("v"))


@query("human_preference", "SELECT count(*) AS n, count(*) FILTER (a > b) AS a_wins, count(*) FILTER (a = b) AS ties FROM (SELECT (props->>'$.k')::INT AS k, count(*) FILTER (event_type = 'click') AS a, count(*) FILTER (event_type = 'purchase') AS b FROM events GROUP BY 1)")
def human_preference(spark, d):
    k = F.get_json_object("props", "$.k").cast("int")
    g = table(spark, d, "events").groupBy(k.alias("k")).agg(F.count_if(F.col("event_type") == "click").alias("a"), F.count_if(F.col("event_type") == "purchase").alias("b"))
    return g.agg(F.count("*").alias("n"), F.count_if(F.col("a") > F.col("b")).alias("a_wins"), F.count_if(F.col("a") == F.col("b")).alias("ties"))


_SQL_JUDGED = f"(SELECT pid, conv_id, {post.sql_judge('response', *post.A)} AS a, {post.sql_judge('response', *post.B)} AS b FROM {post._SQL_QA})"


@query("judge_mean", f"SELECT multi, count(*) AS n, round(avg(a), 6) AS mean FROM (SELECT a, count(*) OVER (PARTITION BY conv_id) > 1 AS multi FROM {_SQL_JUDGED}) GROUP BY multi")
def judge_mean(spark, d):
    """Mean judge score of single- and multi-turn dialogs."""
    q = post.exchanges(table(spark, d, "conversations")).select("conv_id", post.judge(F.col("response"), *post.A).alias("a"))
    return q.select("a", (F.count("*").over(Window.partitionBy("conv_id")) > 1).alias("multi")).groupBy("multi").agg(F.count("*").alias("n"), F.round(F.avg("a"), 6).alias("mean"))


@query("win_rate_raw", f"SELECT count(*) AS n, round(avg(CASE WHEN a > b THEN 1.0 WHEN a = b THEN 0.5 ELSE 0.0 END)::DOUBLE, 6) AS win_rate FROM {_SQL_JUDGED}")
def win_rate(spark, d):
    q = post._judged(spark, d)
    return q.agg(F.count("*").alias("n"), F.round(F.avg(F.when(F.col("a") > F.col("b"), 1.0).when(F.col("a") == F.col("b"), 0.5).otherwise(0.0)), 6).alias("win_rate"))


@query("win_rate_length_controlled")
def lc_win_rate(spark, d):
    """Win rate at equal length: a logistic fit of wins on the difference of lengths, read at zero difference."""
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.feature import VectorAssembler

    s = post.scored(spark, d)
    o = s.select("pid", F.col("rid").alias("other"), F.col("a").alias("oa"), F.length("response").alias("ol"))
    j = s.join(o, "pid").filter("rid < other and a <> oa").select((F.col("a") > F.col("oa")).cast("double").alias("label"), F.tanh((F.length("response") - F.col("ol")) / 200.0).alias("d"))
    rows = VectorAssembler(inputCols=["d"], outputCol="features").transform(j)
    m = LogisticRegression(maxIter=20, regParam=0.01).fit(rows)
    return spark.createDataFrame([(float(1 / (1 + pow(2.718281828459045, -m.intercept))), float(m.coefficients[0]))], "win_rate double, length_weight double")


@query("toxic_classifier")
def toxic_classifier(spark, d):
    """Hashed word counts and a logistic head on labelled documents with an even hash; scores of all documents, beside
    the label where there is one."""
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.feature import HashingTF
    from pyspark.ml.functions import vector_to_array

    w = words(F.coalesce("text", F.lit(""))).alias("w")
    rows = table(spark, d, "documents").select("doc_id", w).join(table(spark, d, "labels").select("doc_id", F.col("toxic").cast("double").alias("label")), "doc_id", "left")
    x = HashingTF(inputCol="w", outputCol="features", numFeatures=1 << 14).transform(rows)
    even = h28(F.col("doc_id").cast("string")) % 2 == 0
    m = LogisticRegression(maxIter=15, regParam=0.05).fit(x.filter(even & F.col("label").isNotNull()))
    return m.transform(x).select("doc_id", F.round(vector_to_array("probability")[1], 4).alias("score"), F.col("label").cast("int").alias("toxic"))


@query("name_hits", f"WITH f AS (SELECT list(word) AS top FROM (SELECT word FROM (SELECT unnest({SQL_WORDS}) AS word FROM documents) GROUP BY word ORDER BY count(*) DESC, word LIMIT 100)) SELECT conv_id, turn, len(list_intersect({SQL_WORDS}, top))::INT AS hits FROM conversations, f WHERE role = 'user'")
def name_hits(spark, d, k: int = 100):
    """Prompts by how many of the 100 commonest words (standing for names) they hold; the list is of fixed size."""
    top = tokenizer._freq(spark, d).orderBy(F.desc("cnt"), "word").limit(k).agg(F.collect_list("word").alias("top"))
    return table(spark, d, "conversations").filter("role = 'user'").crossJoin(F.broadcast(top)).select("conv_id", "turn", F.size(F.array_intersect(words("text"), "top")).alias("hits"))


@query("task_grammar", f"SELECT item_id, array_to_string(list_filter(list_transform(range(1, len(w) + 1), lambda i: CASE WHEN i = {sql_h28('item_id::VARCHAR')} % len(w) + 1 THEN NULL ELSE w[i] END), lambda x: x IS NOT NULL), ' ') AS prompt, array_to_string(w, ' ') AS answer FROM (SELECT item_id, string_split(text, ' ') AS w FROM benchmark)")
def task_grammar(spark, d):
    """A sentence without one word, picked by hash, to be mended."""
    w = table(spark, d, "benchmark").select("item_id", F.split("text", " ").alias("w")).withColumn("at", h28(F.col("item_id").cast("string")) % F.size("w"))
    return w.select("item_id", F.array_join(F.filter("w", lambda x, i: i != F.col("at")), " ").alias("prompt"), F.array_join("w", " ").alias("answer"))


@query("preference_balanced", f"SELECT pid, chosen, rejected FROM {post._SQL_PREF} QUALIFY row_number() OVER (PARTITION BY pid % 2 ORDER BY pid) <= (SELECT min(n) FROM (SELECT count(*) AS n FROM {post._SQL_PREF} GROUP BY pid % 2))")
def balanced(spark, d):
    """As many pairs of either group (parity stands for language) as the smaller has; ranks come from ranges."""
    r = ranked(post.preference_pairs(spark, d).withColumn("g", F.col("pid") % 2), ["g"], ["pid"])
    least = r.groupBy("g").agg(F.count("*").alias("n")).agg(F.min("n").alias("n"))
    return r.join(F.broadcast(least), F.col("rank_") < F.col("n")).select("pid", "chosen", "rejected")


@query("lang_mismatch_rejects", f"SELECT p.pid, arg_min(r.pid, ({sql_h28("p.pid::VARCHAR || '-' || r.pid::VARCHAR")}, r.pid)) AS rejected FROM {post._SQL_QA} p JOIN {post._SQL_QA} r ON {sql_h28('p.pid::VARCHAR')} % {post._SQL_BLOCKS} = {sql_h28('r.pid::VARCHAR')} % {post._SQL_BLOCKS} AND p.conv_id % 2 <> r.conv_id % 2 GROUP BY p.pid")
def mismatch(spark, d):
    """An answer in another language (parity of the dialog stands for it) as the rejected side."""
    q = post.in_blocks(post.exchanges(table(spark, d, "conversations")))
    r = q.select(F.col("pid").alias("rid"), F.col("conv_id").alias("rc"), "block")
    j = q.join(r, "block").filter((F.col("conv_id") % 2) != (F.col("rc") % 2))
    return j.groupBy("pid").agg(F.min_by("rid", F.struct(h28(F.concat_ws("-", "pid", "rid")), "rid")).alias("rejected"))


@query("rag_prompt", f"SELECT qid, string_agg('[' || cid::VARCHAR || '] ' || text, chr(10) ORDER BY cid) AS prompt FROM ({ORACLE['context_fit']}) JOIN documents ON cid = doc_id GROUP BY qid")
def rag_prompt(spark, d):
    """Prompt of a query with the whole texts of its best documents that fit the window."""
    fit = retrieval.context_fit(spark, d).join(table(spark, d, "documents").select(F.col("doc_id").alias("cid"), F.col("text").alias("t")), "cid")
    return fit.groupBy("qid").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("cid", "t"))), lambda x: F.concat(F.lit("["), x["cid"].cast("string"), F.lit("] "), x["t"])), "\n").alias("prompt"))


@query("recency_search", "SELECT user_id, event_id FROM events QUALIFY row_number() OVER (PARTITION BY user_id ORDER BY ts DESC, event_id DESC) <= 3")
def recency(spark, d):
    rn = F.row_number().over(Window.partitionBy("user_id").orderBy(F.desc("ts"), F.desc("event_id")))
    return table(spark, d, "events").withColumn("rn", rn).filter("rn <= 3").select("user_id", "event_id")


@query("mt_average", f"SELECT round(avg(bleu), 3) AS mean, max(bleu) AS best FROM {evaluation._SQL_BLEU}")
def mt_average(spark, d):
    return evaluation._bleu(spark, d).agg(F.round(F.avg("bleu"), 3).alias("mean"), F.max("bleu").alias("best"))


def _trigrams(text: str) -> tuple[np.ndarray, np.ndarray]:
    """Codes of a text's letter trigrams, in order, and how often it has each."""
    x = np.frombuffer(text.encode("utf-32-le"), "<u4").astype(np.int64)
    return np.unique(x[:-2] << 42 | x[1:-1] << 21 | x[2:], return_counts=True)


def _trigram_sums(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        for at in range(0, b.num_rows, 256):
            parts = [_trigrams(t) for t in b.column("t").slice(at, 256).to_pylist()]
            g, of = np.unique(np.concatenate([p[0] for p in parts]), return_inverse=True)
            c = np.zeros(len(g), np.int64)
            np.add.at(c, of, np.concatenate([p[1] for p in parts]))
            yield pa.RecordBatch.from_arrays([pa.array(g), pa.array(c)], names=["g", "c"])


def closeness(docs: DataFrame) -> DataFrame:
    """doc_id, s: cosine, up to a factor, of the letter trigrams of a whole text to those of all English texts. Texts are
    counted in Arrow batches; the reference goes to the workers, a number for each trigram that the language has."""
    t = spread(docs.select("doc_id", "lang", "text")).select("doc_id", "lang", F.lower("text").alias("t")).filter("length(t) >= 3")
    ref = t.filter("lang = 'en'").select("t").mapInArrow(_trigram_sums, "g long, c long").groupBy("g").agg(F.sum("c").alias("r")).toArrow().sort_by("g")
    sent = docs.sparkSession.sparkContext.broadcast((ref["g"].to_numpy(), ref["r"].to_numpy()))

    def products(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names, weights = sent.value
        for b in batches:
            dot, square = [], []
            for x in b.column("t"):
                g, c = _trigrams(x.as_py())
                at = np.searchsorted(names, g)
                known = at < len(names)
                known[known] = names[at[known]] == g[known]
                dot.append(int((c[known] * weights[at[known]]).sum()))
                square.append(int((c * c).sum()))
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(dot, pa.int64()), pa.array(square, pa.int64())], names=["doc_id", "dot", "square"])

    return t.select("doc_id", "t").mapInArrow(products, "doc_id long, dot long, square long").select("doc_id", F.round(F.col("dot") / F.sqrt("square"), 6).alias("s"))


_SQL_TRIGRAMS = "(SELECT doc_id, lang, g, count(*) AS c FROM (SELECT doc_id, lang, unnest(list_transform(range(1, length(t) - 1), lambda i: substr(t, i, 3))) AS g FROM (SELECT doc_id, lang, lower(text) AS t FROM documents) WHERE length(t) >= 3) GROUP BY ALL)"


@query("proximity_batches", f"WITH g AS MATERIALIZED {_SQL_TRIGRAMS}, r AS (SELECT g, sum(c) AS r FROM g WHERE lang = 'en' GROUP BY g), s AS (SELECT doc_id, round((coalesce(sum(c * r), 0) / sqrt(sum(c * c)))::DOUBLE, 6) AS s FROM g LEFT JOIN r USING (g) GROUP BY doc_id) SELECT doc_id, ntile(5) OVER (ORDER BY -s, doc_id)::INT AS batch FROM s")
def proximity(spark, d):
    """Documents in five batches of equal size by the cosine of their letter trigrams to those of the reference language,
    the nearest first; the batches' ends come from ranks over ranges."""
    cos = dedup.reliable(closeness(table(spark, d, "documents")).withColumn("far", -F.col("s")))
    cuts = cut_points(cos, ["far", "doc_id"], 5)
    return cos.crossJoin(F.broadcast(cuts)).select("doc_id", (1 + F.size(F.filter("cuts", lambda c: c <= F.struct("far", "doc_id")))).alias("batch"))


@query("map_in_arrow_sig", f"SELECT doc_id, sig[1] AS first, sig[{dedup.BANDS * dedup.ROWS}] AS last FROM ({dedup.sql_signatures()})")
def sig(spark, d):
    """Two entries of each signature: what a batch operator over whole texts returns."""
    return dedup.minhash_signatures(table(spark, d, "documents")).select("doc_id", F.col("sig")[0].alias("first"), F.get("sig", F.lit(dedup.BANDS * dedup.ROWS - 1)).alias("last"))


@query("udf_arrow_wer")
def udf_wer(spark, d):
    """Word errors of each hypothesis by a scalar Arrow UDF, a column beside the built-in ones."""

    @F.arrow_udf("long")
    def errors(hyp: pa.Array, ref: pa.Array) -> pa.Array:
        return pa.array([evaluation.word_errors(h.split(" "), r.split(" ")) for h, r in zip(hyp.to_pylist(), ref.to_pylist())], pa.int64())

    return evaluation.hypotheses(table(spark, d, "benchmark")).select("system", "id", errors("hyp", "ref").alias("errors"))


@query("udf_grouped_agg", "SELECT event_type, list(v ORDER BY v)[(count(*) // 2 + 1)::INT] AS median FROM (SELECT event_type, round(value, 1) AS v FROM events WHERE value IS NOT NULL) GROUP BY event_type")
def udf_grouped(spark, d):
    """A grouped Arrow aggregate: the upper median of a group's values to one place. Equal values are counted first, so a
    group's rows in the worker are its distinct values, not its events."""

    def median(group: pa.Table) -> pa.Table:
        group = group.sort_by("v")
        upto = np.cumsum(group.column("n").to_numpy())
        at = int(np.searchsorted(upto, upto[-1] // 2, "right"))
        return pa.table({"event_type": [group.column("event_type")[0].as_py()], "median": [group.column("v")[at].as_py()]})

    counts = table(spark, d, "events").filter("value is not null").groupBy("event_type", F.round("value", 1).alias("v")).agg(F.count("*").alias("n"))
    return counts.groupBy("event_type").applyInArrow(median, "event_type string, median double")


class LineChunks:
    """Table function: line-bounded chunks of a text, at most `most` words each, a greedy fold over its lines."""

    def eval(self, text: str, most: int) -> Iterator[tuple[int, int]]:
        pos = held = 0
        for line in (text or "").split("\n"):
            n = len(line.split())
            if held and held + n > most:
                yield pos, held
                pos, held = pos + 1, 0
            while held + n > most:
                yield pos, most
                pos, n = pos + 1, n - (most - held)
                held = 0
            held += n
        if held:
            yield pos, held


@query("udtf_chunks")
def udtf_chunks(spark, d):
    """Line-bounded chunks of at most 60 words through a table function, joined laterally to each document."""
    chunks = F.udtf(LineChunks, returnType="pos int, n int", useArrow=True)
    return table(spark, d, "documents").select("doc_id", "text").lateralJoin(chunks(F.col("text").outer(), F.lit(60))).select("doc_id", "pos", "n")


@query("json_roundtrip", "SELECT doc_id, lang, n_chars FROM documents")
def json_roundtrip(spark, d):
    """Records written as JSON lines and read with a schema."""
    from ..sources.files import read_records, write_records

    return read_records(spark, write_records(table(spark, d, "documents").select("doc_id", "lang", "n_chars"), "json"), "json", "doc_id long, lang string, n_chars long")


@query("partitioned_scan", "SELECT doc_id, n_chars FROM documents WHERE lang = 'fr'")
def partitioned_scan(spark, d):
    """A table partitioned by language; the filter reads one folder."""
    from ..sources.files import read_records, write_records

    path = write_records(table(spark, d, "documents").select("doc_id", "n_chars", "lang"), "parquet", "lang")
    return read_records(spark, path, "parquet", "doc_id long, n_chars long, lang string").filter("lang = 'fr'").select("doc_id", "n_chars")
