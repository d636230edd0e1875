"""Chunks, vector search, re-ranking, BM25, routing, attribution, averaging and taxonomy coverage."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..catalog import query, table
from ..functions.text import SQL_WORDS, ratio, sql_ratio, words
from ..plans.spread import spread
from .dedup import cosine

TOP, KEPT, CHUNK, OVERLAP = 20, 4, 2048, 50
#: The queries of a search: one vector in twenty.
ASKED = "vec_id % 20 = 0"


@query("chunk_fixed", f"SELECT doc_id, pos::INT AS pos, len(w[s:s+255])::INT AS n_tok, md5(array_to_string(w[s:s+255], ' ')) AS digest FROM (SELECT doc_id, w, unnest(range(0, greatest(1, ((len(w) - 50 + 205) // 206)))) AS pos FROM (SELECT doc_id, {SQL_WORDS} AS w FROM documents) WHERE len(w) > 0) t, LATERAL (SELECT pos * 206 + 1 AS s)")
def chunks(spark, d, size: int = 256, overlap: int = 50):
    """Chunks of `size` words, each beginning with the last `overlap` words of the one before."""
    step = size - overlap
    w = table(spark, d, "documents").select("doc_id", words("text").alias("w")).filter("size(w) > 0")
    n = F.greatest(F.lit(1), F.floor((F.size("w") - overlap + step - 1) / step))
    each = w.select("doc_id", "w", F.explode(F.sequence(F.lit(0).cast("bigint"), n - 1)).alias("p"))
    part = F.slice("w", (F.col("p") * step + 1).cast("int"), F.lit(size))
    return each.select("doc_id", F.col("p").cast("int").alias("pos"), F.size(part).alias("n_tok"), F.md5(F.array_join(part, " ").cast("binary")).alias("digest"))


_SQL_TOP = f"(SELECT q.vec_id AS qid, c.vec_id AS cid, round(list_dot_product(q.embedding::DOUBLE[], c.embedding::DOUBLE[]), 6) AS sim FROM embeddings q JOIN embeddings c ON q.vec_id <> c.vec_id WHERE q.{ASKED} AND sim >= 0.1 QUALIFY row_number() OVER (PARTITION BY q.vec_id ORDER BY sim DESC, c.vec_id) <= 20)"


#: Bytes of query vectors that a pass over the corpus takes to the tasks.
PASS_BYTES = 32_000_000


class _Best:
    """The best k of each query so far, as (query, similarity, id) arrays."""

    def __init__(self, k: int, least: float, n: int):
        self.k, self.bound, self.held, self.size = k, np.full(n, least), [], 0

    def add(self, q: np.ndarray, sim: np.ndarray, cid: np.ndarray) -> None:
        self.held.append((q, sim, cid))
        self.size += len(q)
        if self.size > 4 * self.k * len(self.bound) + 100_000:
            self.cut()

    def cut(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        q, sim, cid = (np.concatenate(x) for x in zip(*self.held)) if self.held else (np.zeros(0, np.int64), np.zeros(0), np.zeros(0, np.int64))
        order = np.lexsort((cid, -sim, q))
        q, sim, cid = q[order], sim[order], cid[order]
        first = np.searchsorted(q, q, "left")
        place = np.arange(len(q)) - first
        last = place == self.k - 1
        self.bound[q[last]] = np.maximum(self.bound[q[last]], sim[last])
        top = place < self.k
        self.held, self.size = [(q[top], sim[top], cid[top])], int(top.sum())
        return self.held[0]


def _nearest(ids: np.ndarray, vectors: np.ndarray, k: int, least: float):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        best = _Best(k, least, len(ids))
        for batch in batches:
            for at in range(0, batch.num_rows, 2048):
                part = batch.slice(at, 2048)
                cid, x = part.column("vec_id").to_numpy(), part.column("embedding").flatten().to_numpy().reshape(part.num_rows, -1).astype(np.float64)
                for lo in range(0, len(ids), 1024):
                    sim = np.round(vectors[lo : lo + 1024] @ x.T, 6)
                    q, c = np.nonzero((sim >= best.bound[lo : lo + 1024, None]) & (ids[lo : lo + 1024, None] != cid[None, :]))
                    best.add(q + lo, sim[q, c], cid[c])
        q, sim, cid = best.cut()
        yield pa.RecordBatch.from_arrays([pa.array(ids[q]), pa.array(cid), pa.array(sim)], names=["qid", "cid", "sim"])

    return run


def search(queries: DataFrame, corpus: DataFrame, k: int = TOP, least: float = 0.1) -> DataFrame:
    """(qid, cid, sim): top k above a threshold by exact similarity, ties by id. Queries are a stated set; those of
    PASS_BYTES of vectors go to all tasks at a time, each of which keeps its own best k of a query, so at most k rows of a
    query and task are sent. A vector or id that is missing is left out."""
    queries, corpus = (x.filter("vec_id is not null and embedding is not null").select(F.col("vec_id").cast("long").alias("vec_id"), "embedding") for x in (queries, corpus))
    n, dim = queries.agg(F.count("*"), F.max(F.size("embedding"))).first()
    out, passes = None, max(1, -(-n * (dim or 1) * 8 // PASS_BYTES))
    for i in range(passes):
        asked = queries.filter(F.pmod(F.xxhash64("vec_id"), F.lit(passes)) == i).toArrow().combine_chunks()
        ids = asked.column("vec_id").to_numpy()
        vectors = np.array(asked.column("embedding").to_pylist(), np.float64).reshape(len(ids), -1) if len(ids) else np.zeros((0, dim or 1))
        one = corpus.mapInArrow(_nearest(ids, vectors, k, least), "qid long, cid long, sim double")
        out = one if out is None else out.unionByName(one)
    return out.withColumn("rn", F.row_number().over(Window.partitionBy("qid").orderBy(F.desc("sim"), "cid"))).filter(F.col("rn") <= k).select("qid", "cid", "sim")


@query("vector_topk", f"SELECT * FROM {_SQL_TOP}")
def _topk(spark, d):
    e = table(spark, d, "embeddings")
    return search(e.filter(ASKED), e)


@query("rerank_top4", f"SELECT qid, cid FROM {_SQL_TOP} JOIN embeddings ON cid = vec_id QUALIFY row_number() OVER (PARTITION BY qid ORDER BY round(sim + 0.01 * label, 6) DESC, cid) <= 4")
def rerank(spark, d):
    """A second score (here the similarity with a bonus by label) orders the 20 and keeps 4."""
    second = F.round(F.col("sim") + 0.01 * F.col("label"), 6)
    j = _topk(spark, d).join(table(spark, d, "embeddings").select(F.col("vec_id").alias("cid"), "label"), "cid")
    return j.withColumn("rn", F.row_number().over(Window.partitionBy("qid").orderBy(F.desc(second), "cid"))).filter(F.col("rn") <= KEPT).select("qid", "cid")


@query("context_fit", f"SELECT qid, cid FROM (SELECT qid, cid, sum(n_chars) OVER (PARTITION BY qid ORDER BY sim DESC, cid) AS upto FROM {_SQL_TOP} JOIN documents ON cid = doc_id) WHERE upto <= 8000")
def context_fit(spark, d, budget: int = 8000):
    upto = F.sum("n_chars").over(Window.partitionBy("qid").orderBy(F.desc("sim"), "cid"))
    return _topk(spark, d).join(table(spark, d, "documents").select(F.col("doc_id").alias("cid"), "n_chars"), "cid").withColumn("upto", upto).filter(F.col("upto") <= budget).select("qid", "cid")


@query("threshold_calibration", f"SELECT t / 20.0::DOUBLE AS threshold, count(*) AS n, {sql_ratio('count(*) FILTER (a.label = b.label)', 'count(*)')} AS precision FROM {_SQL_TOP} JOIN embeddings a ON a.vec_id = qid JOIN embeddings b ON b.vec_id = cid JOIN (SELECT unnest(range(2, 12)) AS t) ON sim >= t / 20.0 GROUP BY t")
def calibrate(spark, d):
    """Precision of neighbours of the same class at each threshold of a grid."""
    e = table(spark, d, "embeddings")
    j = _topk(spark, d).join(e.select(F.col("vec_id").alias("qid"), F.col("label").alias("a")), "qid").join(e.select(F.col("vec_id").alias("cid"), F.col("label").alias("b")), "cid")
    g = j.join(spark.range(2, 12).select((F.col("id") / 20.0).alias("threshold")), F.col("sim") >= F.col("threshold"))
    return g.groupBy("threshold").agg(F.count("*").alias("n"), ratio(F.count_if(F.col("a") == F.col("b")), F.count("*")).alias("precision"))


_SQL_BM25 = f"""(WITH t AS MATERIALIZED (SELECT doc_id, word, count(*) AS tf, any_value(n) AS n FROM (SELECT doc_id, unnest(w) AS word, len(w) AS n FROM (SELECT doc_id, {SQL_WORDS} AS w FROM documents)) GROUP BY doc_id, word),
  s AS (SELECT count(*) AS docs, avg(n) AS mean FROM (SELECT doc_id, any_value(n) AS n FROM t GROUP BY doc_id)), q AS (SELECT item_id, unnest(list_distinct({SQL_WORDS})) AS word FROM benchmark), f AS (SELECT word, count(*) AS df FROM t GROUP BY word)
  SELECT item_id, doc_id, round(sum(ln(1 + (docs - df + 0.5::DOUBLE) / (df + 0.5::DOUBLE)) * tf * 2.2 / (tf + 1.2::DOUBLE * (0.25 + 0.75 * n / mean))), 5) AS score FROM q JOIN t USING (word) JOIN f USING (word), s GROUP BY item_id, doc_id QUALIFY row_number() OVER (PARTITION BY item_id ORDER BY score DESC, doc_id) <= 5)"""


def bm25(docs: DataFrame, queries: DataFrame, k: int = 5, k1: float = 1.2, b: float = 0.75) -> DataFrame:
    """(item_id, doc_id, score): only postings of query words are kept before anything is joined to them."""
    w = spread(docs.select("doc_id", "text")).select("doc_id", words("text").alias("w")).withColumn("n", F.size("w")).filter("n > 0")
    q = queries.select("item_id", F.explode(F.array_distinct(words("text"))).alias("word"))
    t = w.select("doc_id", "n", F.explode("w").alias("word")).join(q.select("word").distinct(), "word", "left_semi").groupBy("doc_id", "word", "n").agg(F.count("*").alias("tf"))
    f = t.groupBy("word").agg(F.count("*").alias("df"))
    s = w.agg(F.count("*").alias("docs"), F.avg("n").alias("mean"))
    idf = F.log(1 + (F.col("docs") - F.col("df") + 0.5) / (F.col("df") + 0.5))
    one = idf * F.col("tf") * (k1 + 1) / (F.col("tf") + k1 * (1 - b + b * F.col("n") / F.col("mean")))
    g = q.join(t, "word").join(f, "word").join(F.broadcast(s)).groupBy("item_id", "doc_id").agg(F.round(F.sum(one), 5).alias("score"))
    return g.withColumn("rn", F.row_number().over(Window.partitionBy("item_id").orderBy(F.desc("score"), "doc_id"))).filter(F.col("rn") <= k).select("item_id", "doc_id", "score")


@query("bm25_scores", f"SELECT * FROM {_SQL_BM25}")
def _bm25(spark, d):
    return bm25(table(spark, d, "documents"), table(spark, d, "benchmark"))


#: Ordered routes: the first pattern that a request matches.
ROUTES = (("unsafe", "password|secret|token"), ("image", "draw|image|picture"), ("recent", "news|today|latest"), ("stem", "code|math|[0-9]{2}"))
_SQL_ROUTE = "CASE " + " ".join(f"WHEN regexp_matches(lower(text), '{p}') THEN '{r}'" for r, p in ROUTES) + " ELSE 'general' END"


def route(text: Column) -> Column:
    out = None
    for r, p in ROUTES:
        out = F.when(F.lower(text).rlike(p), r) if out is None else out.when(F.lower(text).rlike(p), r)
    return out.otherwise("general")


@query("route_requests", f"SELECT conv_id, turn, {_SQL_ROUTE} AS route FROM conversations WHERE role = 'user'")
def _route(spark, d):
    return table(spark, d, "conversations").filter("role = 'user'").select("conv_id", "turn", route(F.col("text")).alias("route"))


@query("route_stats", f"SELECT {_SQL_ROUTE} AS route, count(*) AS n FROM conversations WHERE role = 'user' GROUP BY 1")
def _route_stats(spark, d):
    return _route(spark, d).groupBy("route").agg(F.count("*").alias("n"))


@query("weight_average", "SELECT label, list(m ORDER BY i) AS v FROM (SELECT label, i, round(avg(embedding[i]::DOUBLE), 6) AS m FROM embeddings, (SELECT unnest(range(1, 65)) AS i) GROUP BY ALL) GROUP BY label")
def weight_average(spark, d):
    """Mean of the vectors of a group, as checkpoints of a model are averaged."""
    m = table(spark, d, "embeddings").select("label", F.posexplode("embedding").alias("i", "v")).groupBy("label", "i").agg(F.round(F.avg(F.col("v").cast("double")), 6).alias("m"))
    return m.groupBy("label").agg(F.transform(F.array_sort(F.collect_list(F.struct("i", "m"))), lambda x: x["m"]).alias("v"))


@query("taxonomy_coverage", "SELECT r_name, n_name, count(c_custkey) AS n FROM region JOIN nation ON n_regionkey = r_regionkey LEFT JOIN customer ON c_nationkey = n_nationkey GROUP BY ROLLUP (r_name, n_name)")
def coverage(spark, d):
    """Items under each node of a concept tree, with its leaves that have none."""
    t = lambda n: table(spark, d, n)
    j = t("region").join(t("nation"), F.col("n_regionkey") == F.col("r_regionkey")).join(t("customer"), F.col("c_nationkey") == F.col("n_nationkey"), "left")
    return j.rollup("r_name", "n_name").agg(F.count("c_custkey").alias("n"))


@query("embedding_similarity", "SELECT a.vec_id, round(list_dot_product(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 6) AS sim FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1")
def similarity(spark, d):
    """Cosine of neighbours: a stand-in for a learned metric, not the metric itself."""
    e = table(spark, d, "embeddings")
    return e.join(e.select((F.col("vec_id") - 1).alias("vec_id"), F.col("embedding").alias("o")), "vec_id").select("vec_id", F.round(cosine(F.col("embedding"), F.col("o")), 6).alias("sim"))


_SQL_SENT = f"(SELECT item_id, pos, sent FROM (SELECT item_id, unnest(s) AS sent, unnest(range(1, len(s) + 1)) AS pos FROM (SELECT item_id, list_filter(string_split(text, '. '), lambda x: x <> '') AS s FROM benchmark)))"


@query("attribute_sentences", f"WITH s AS MATERIALIZED (SELECT item_id, pos, unnest(list_distinct({SQL_WORDS.replace('lower(text)', 'lower(sent)')})) AS word FROM {_SQL_SENT}), n AS (SELECT item_id, pos, count(*) AS n FROM s GROUP BY ALL), e AS MATERIALIZED (SELECT doc_id, unnest(list_distinct({SQL_WORDS})) AS word FROM documents JOIN (SELECT DISTINCT doc_id FROM {_SQL_BM25}) USING (doc_id)), h AS (SELECT s.item_id, pos, b.doc_id, count(*) AS hit FROM s JOIN {_SQL_BM25} b USING (item_id) JOIN e ON e.doc_id = b.doc_id AND e.word = s.word GROUP BY ALL) SELECT item_id, pos::INT AS pos, arg_max(doc_id, (hit, -doc_id)) AS doc_id, round(max(hit)::DOUBLE / any_value(n), 6) AS support FROM h JOIN n USING (item_id, pos) GROUP BY item_id, pos")
def attribute(spark, d):
    """Each sentence with the evidence document that holds most of its words, among the query's best."""
    b = table(spark, d, "benchmark")
    s = b.select("item_id", F.posexplode(F.filter(F.split("text", r"\. "), lambda x: x != "")).alias("p", "sent")).select("item_id", (F.col("p") + 1).alias("pos"), F.array_distinct(words("sent")).alias("w"))
    docs = table(spark, d, "documents")
    best = bm25(docs, b).select("item_id", "doc_id")
    ev = docs.join(best.select("doc_id").distinct(), "doc_id", "left_semi").select("doc_id", F.array_distinct(words("text")).alias("e"))
    j = s.join(best, "item_id").join(ev, "doc_id").select("item_id", "pos", "doc_id", F.size("w").alias("n"), F.size(F.array_intersect("w", "e")).alias("hit")).filter("hit > 0")
    return j.groupBy("item_id", "pos").agg(F.max_by("doc_id", F.struct("hit", -F.col("doc_id"))).alias("doc_id"), F.round(F.max("hit") / F.first("n"), 6).alias("support"))
