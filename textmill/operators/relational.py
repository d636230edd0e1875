"""The relational operators around the methods: filters, joins, aggregates, windows, top-k, sets, functions."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..catalog import query, table
from ..plans.components import reliable


def dec(c: str) -> F.Column:
    return F.col(c).cast("decimal(18,2)")


@query("filter_project", "SELECT l_orderkey, l_linenumber, l_quantity * 2 AS q2 FROM lineitem WHERE l_quantity BETWEEN 10 AND 20 AND l_returnflag IN ('A', 'R') AND l_linestatus LIKE 'F%'")
def _filter(spark, d):
    return table(spark, d, "lineitem").filter("l_quantity BETWEEN 10 AND 20 AND l_returnflag IN ('A', 'R') AND l_linestatus LIKE 'F%'").select("l_orderkey", "l_linenumber", (F.col("l_quantity") * 2).alias("q2"))


@query("case_bucket", "SELECT CASE WHEN n_chars < 500 THEN 'short' WHEN n_chars < 3000 THEN 'middle' ELSE 'long' END AS bucket, count(*) AS n FROM documents GROUP BY 1")
def _case(spark, d):
    b = F.when(F.col("n_chars") < 500, "short").when(F.col("n_chars") < 3000, "middle").otherwise("long")
    return table(spark, d, "documents").groupBy(b.alias("bucket")).agg(F.count("*").alias("n"))


@query("null_semantics", "SELECT coalesce(quality, -1) AS q, (quality IS NOT DISTINCT FROM NULL) AS is_null, count(*) AS n, count(quality) AS n_known FROM documents LEFT JOIN labels USING (doc_id) GROUP BY ALL")
def _nulls(spark, d):
    j = table(spark, d, "documents").join(table(spark, d, "labels"), "doc_id", "left")
    return j.groupBy(F.coalesce("quality", F.lit(-1)).alias("q"), F.col("quality").eqNullSafe(F.lit(None)).alias("is_null")).agg(F.count("*").alias("n"), F.count("quality").alias("n_known"))


def _orders(spark, d) -> tuple[DataFrame, DataFrame]:
    return table(spark, d, "orders"), table(spark, d, "customer")


@query("join_inner", "SELECT o_orderkey, c_name FROM orders JOIN customer ON o_custkey = c_custkey")
def _inner(spark, d):
    o, c = _orders(spark, d)
    return o.join(c, o.o_custkey == c.c_custkey).select("o_orderkey", "c_name")


@query("join_left", "SELECT doc_id, quality FROM documents LEFT JOIN labels USING (doc_id)")
def _left(spark, d):
    return table(spark, d, "documents").join(table(spark, d, "labels"), "doc_id", "left").select("doc_id", "quality")


@query("join_full", "SELECT c_custkey, count(o_orderkey) AS n FROM customer FULL JOIN (SELECT * FROM orders WHERE o_orderstatus = 'P') ON o_custkey = c_custkey GROUP BY c_custkey")
def _full(spark, d):
    o, c = _orders(spark, d)
    return c.join(o.filter("o_orderstatus = 'P'"), F.col("o_custkey") == F.col("c_custkey"), "full").groupBy("c_custkey").agg(F.count("o_orderkey").alias("n"))


@query("join_broadcast", "SELECT p_brand, count(*) AS n FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY p_brand")
def _broadcast(spark, d):
    """Spark chooses the broadcast by the size it measures; no hint forces a side that may have grown."""
    return table(spark, d, "lineitem").join(table(spark, d, "part").select("p_partkey", "p_brand"), F.col("l_partkey") == F.col("p_partkey")).groupBy("p_brand").agg(F.count("*").alias("n"))


@query("join_semi", "SELECT doc_id FROM documents SEMI JOIN labels USING (doc_id)")
def _semi(spark, d):
    return table(spark, d, "documents").join(table(spark, d, "labels"), "doc_id", "left_semi").select("doc_id")


@query("join_anti", "SELECT doc_id FROM documents ANTI JOIN labels USING (doc_id)")
def _anti(spark, d):
    return table(spark, d, "documents").join(table(spark, d, "labels"), "doc_id", "left_anti").select("doc_id")


@query("join_theta", "SELECT a.r_name AS r1, b.r_name AS r2 FROM region a JOIN region b ON a.r_regionkey < b.r_regionkey")
def _theta(spark, d):
    r = table(spark, d, "region")
    return r.alias("a").join(r.alias("b"), F.col("a.r_regionkey") < F.col("b.r_regionkey")).select(F.col("a.r_name").alias("r1"), F.col("b.r_name").alias("r2"))


@query("join_range_bins", "SELECT lo, count(*) AS n FROM documents JOIN (SELECT unnest(range(0, 40000, 500)) AS lo) ON n_chars >= lo AND n_chars < lo + 500 GROUP BY lo")
def _range(spark, d):
    """A range join as an equi-join on the bin number."""
    bins = spark.range(0, 80).select((F.col("id") * 500).alias("lo"), F.col("id").alias("bin"))
    return table(spark, d, "documents").withColumn("bin", F.floor(F.col("n_chars") / 500)).join(bins, "bin").groupBy("lo").agg(F.count("*").alias("n"))


@query("join_interval", "SELECT a.event_id AS e1, b.event_id AS e2 FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR WHERE a.event_type = 'view' AND b.event_type = 'purchase'")
def _interval(spark, d):
    """Hour buckets make the interval a key: an event looks into its own bucket and the next."""
    e = table(spark, d, "events").withColumn("hour", F.floor(F.unix_timestamp(F.col("ts").cast("timestamp")) / 3600))
    a = e.filter("event_type = 'view'").select("user_id", F.col("ts").alias("t1"), F.col("event_id").alias("e1"), F.explode(F.array("hour", F.col("hour") + 1)).alias("hour"))
    b = e.filter("event_type = 'purchase'").select("user_id", F.col("ts").alias("t2"), F.col("event_id").alias("e2"), "hour")
    return a.join(b, ["user_id", "hour"]).filter("t2 > t1 AND t2 <= t1 + INTERVAL 1 HOUR").select("e1", "e2")


def join_asof(left: DataFrame, right: DataFrame, by: str, ts: str, value: str, name: str) -> DataFrame:
    """left with the value of the last earlier row of right with the same key: one sorted pass over the union of both."""
    u = left.withColumn("v_", F.lit(None).cast(right.schema[value].dataType)).withColumn("side_", F.lit(0)).unionByName(
        right.select(by, ts, F.col(value).alias("v_"), F.lit(1).alias("side_")), allowMissingColumns=True
    )
    w = Window.partitionBy(by).orderBy(ts, "side_").rowsBetween(Window.unboundedPreceding, -1)
    return u.withColumn(name, F.last("v_", ignorenulls=True).over(w)).filter("side_ = 0").drop("v_", "side_")


@query("join_asof", "SELECT event_id, (SELECT max(b.event_id) FROM events b WHERE b.user_id = a.user_id AND b.event_type = 'error' AND b.ts < a.ts AND b.ts = (SELECT max(c.ts) FROM events c WHERE c.user_id = a.user_id AND c.event_type = 'error' AND c.ts < a.ts)) AS last_error FROM events a WHERE event_type = 'purchase'")
def _asof(spark, d):
    e = table(spark, d, "events").select("event_id", "user_id", "ts", "event_type")
    return join_asof(e.filter("event_type = 'purchase'").drop("event_type"), e.filter("event_type = 'error'"), "user_id", "ts", "event_id", "last_error").select("event_id", "last_error")


@query("join_skew_salted", "SELECT p_type, sum(l_quantity)::DOUBLE AS qty FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY p_type")
def _salted(spark, d, salts: int = 4):
    l = table(spark, d, "lineitem").select("l_partkey", "l_quantity", F.pmod(F.xxhash64("l_orderkey", "l_linenumber"), F.lit(salts)).alias("salt"))
    p = table(spark, d, "part").select("p_partkey", "p_type", F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit(salts - 1).cast("bigint"))).alias("salt"))
    return l.join(p, (F.col("l_partkey") == F.col("p_partkey")) & (l.salt == p.salt)).groupBy("p_type").agg(F.sum("l_quantity").alias("qty"))


@query("agg_pricing_summary", """SELECT l_returnflag, l_linestatus, sum(l_quantity) AS sum_qty, sum(l_extendedprice::DECIMAL(18,2))::DOUBLE AS sum_price, sum(l_extendedprice::DECIMAL(18,2) * (1 - l_discount::DECIMAL(18,2)))::DOUBLE AS sum_disc, round(avg(l_discount::DECIMAL(18,2))::DOUBLE, 6) AS avg_disc, count(*) AS n FROM lineitem WHERE l_shipdate <= TIMESTAMP '1998-09-02' GROUP BY ALL""")
def _pricing(spark, d):
    return (
        table(spark, d, "lineitem").filter("l_shipdate <= TIMESTAMP_NTZ '1998-09-02'").groupBy("l_returnflag", "l_linestatus")
        .agg(F.sum("l_quantity").alias("sum_qty"), F.sum(dec("l_extendedprice")).cast("double").alias("sum_price"), F.sum(dec("l_extendedprice") * (1 - dec("l_discount"))).cast("double").alias("sum_disc"), F.round(F.avg(dec("l_discount")).cast("double"), 6).alias("avg_disc"), F.count("*").alias("n"))
    )


@query("star_join_revenue", """SELECT r_name, n_name, sum(l_extendedprice::DECIMAL(18,2) * (1 - l_discount::DECIMAL(18,2)))::DOUBLE AS revenue FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ALL""")
def _star(spark, d):
    t = lambda n: table(spark, d, n)
    j = t("lineitem").join(t("orders"), F.col("l_orderkey") == F.col("o_orderkey")).join(t("customer"), F.col("o_custkey") == F.col("c_custkey")).join(t("nation"), F.col("c_nationkey") == F.col("n_nationkey")).join(t("region"), F.col("n_regionkey") == F.col("r_regionkey"))
    return j.groupBy("r_name", "n_name").agg(F.sum(dec("l_extendedprice") * (1 - dec("l_discount"))).cast("double").alias("revenue"))


@query("agg_distinct", "SELECT event_type, count(DISTINCT user_id) AS users, count(*) AS n FROM events GROUP BY event_type")
def _distinct(spark, d):
    return table(spark, d, "events").groupBy("event_type").agg(F.count_distinct("user_id").alias("users"), F.count("*").alias("n"))


@query("agg_filtered", "SELECT user_id, count(*) FILTER (event_type = 'error') AS errors, count(*) FILTER (event_type = 'purchase') AS purchases FROM events GROUP BY user_id")
def _filtered(spark, d):
    return table(spark, d, "events").groupBy("user_id").agg(F.count_if(F.col("event_type") == "error").alias("errors"), F.count_if(F.col("event_type") == "purchase").alias("purchases"))


@query("agg_collect_sorted", "SELECT conv_id, string_agg(role, '>' ORDER BY turn) AS roles FROM conversations GROUP BY conv_id")
def _collect(spark, d):
    return table(spark, d, "conversations").groupBy("conv_id").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("turn", "role"))), lambda x: x["role"]), ">").alias("roles"))


for _kind, _sql in (("rollup", "ROLLUP (lang, source)"), ("cube", "CUBE (lang, source)")):

    def _grouped(spark, d, kind=_kind):
        return getattr(table(spark, d, "documents"), kind)("lang", "source").agg(F.count("*").alias("n"), F.sum("n_chars").alias("chars"), F.grouping_id().cast("bigint").alias("gid"))

    query(f"agg_{_kind}", f"SELECT lang, source, count(*) AS n, sum(n_chars)::BIGINT AS chars, grouping_id(lang, source)::BIGINT AS gid FROM documents GROUP BY {_sql}")(_grouped)


@query("agg_grouping_sets", "SELECT lang, source, count(*) AS n FROM documents GROUP BY GROUPING SETS ((lang), (source), ())")
def _sets(spark, d):
    return table(spark, d, "documents").groupingSets([["lang"], ["source"], []], "lang", "source").agg(F.count("*").alias("n"))


@query("agg_approx_distinct")
def _approx(spark, d):
    return table(spark, d, "events").groupBy("event_type").agg(F.approx_count_distinct("user_id", 0.02).alias("users"))


@query("agg_approx_percentile")
def _approx_percentile(spark, d):
    return table(spark, d, "events").groupBy("event_type").agg(F.percentile_approx("value", [0.5, 0.95], 10000).alias("p"))


@query("pivot_feedback", "SELECT user_id, count(*) FILTER (event_type = 'click') AS click, count(*) FILTER (event_type = 'error') AS error FROM events GROUP BY user_id")
def _pivot(spark, d):
    return table(spark, d, "events").groupBy("user_id").pivot("event_type", ["click", "error"]).count().fillna(0)


@query("unpivot_signals", "SELECT doc_id, 'chars' AS name, n_chars AS v FROM documents UNION ALL SELECT doc_id, 'bytes', strlen(text) FROM documents")
def _unpivot(spark, d):
    return table(spark, d, "documents").select("doc_id", F.col("n_chars").alias("chars"), F.octet_length("text").cast("bigint").alias("bytes")).unpivot("doc_id", ["chars", "bytes"], "name", "v")


def _window(name: str, sql: str, columns):
    def run(spark, d):
        return table(spark, d, "orders").select("o_orderkey", *columns())

    query(name, f"SELECT o_orderkey, {sql} FROM orders")(run)


def _w():
    return Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")


_S = "OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)"
_window("win_rank", "row_number() OVER (PARTITION BY o_custkey ORDER BY o_orderpriority, o_orderkey)::INT AS rn, rank() OVER (PARTITION BY o_custkey ORDER BY o_orderpriority)::INT AS rk, dense_rank() OVER (PARTITION BY o_custkey ORDER BY o_orderpriority)::INT AS dr",
        lambda: [F.row_number().over(Window.partitionBy("o_custkey").orderBy("o_orderpriority", "o_orderkey")).alias("rn"), F.rank().over(Window.partitionBy("o_custkey").orderBy("o_orderpriority")).alias("rk"), F.dense_rank().over(Window.partitionBy("o_custkey").orderBy("o_orderpriority")).alias("dr")])
_window("win_running", f"sum(o_totalprice::DECIMAL(18,2)) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS UNBOUNDED PRECEDING)::DOUBLE AS running", lambda: [F.sum(dec("o_totalprice")).over(_w().rowsBetween(Window.unboundedPreceding, 0)).cast("double").alias("running")])
_window("win_lag", f"lag(o_orderkey) {_S} AS before, lead(o_orderkey) {_S} AS after", lambda: [F.lag("o_orderkey").over(_w()).alias("before"), F.lead("o_orderkey").over(_w()).alias("after")])
_window("win_moving", "round(avg(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 4) AS moving", lambda: [F.round(F.avg("o_totalprice").over(_w().rowsBetween(-2, 0)), 4).alias("moving")])
_window("win_ntile", f"ntile(4) {_S}::INT AS quarter", lambda: [F.ntile(4).over(_w()).alias("quarter")])
_window("win_first_last", "first_value(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS f, last_value(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS l",
        lambda: [F.first("o_orderkey").over(_w().rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)).alias("f"), F.last("o_orderkey").over(_w().rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)).alias("l")])


@query("topk_global", "SELECT l_orderkey, l_linenumber, l_extendedprice FROM lineitem ORDER BY l_extendedprice DESC, l_orderkey, l_linenumber LIMIT 20")
def _topk(spark, d):
    return table(spark, d, "lineitem").orderBy(F.desc("l_extendedprice"), "l_orderkey", "l_linenumber").limit(20).select("l_orderkey", "l_linenumber", "l_extendedprice")


@query("topk_per_group", "SELECT source, doc_id FROM documents QUALIFY row_number() OVER (PARTITION BY source ORDER BY n_chars DESC, doc_id) <= 3")
def _topk_group(spark, d):
    return table(spark, d, "documents").withColumn("rn", F.row_number().over(Window.partitionBy("source").orderBy(F.desc("n_chars"), "doc_id"))).filter("rn <= 3").select("source", "doc_id")


@query("sort_offset", "SELECT doc_id FROM documents ORDER BY n_chars, doc_id LIMIT 10 OFFSET 5")
def _offset(spark, d):
    return table(spark, d, "documents").orderBy("n_chars", "doc_id").offset(5).limit(10).select("doc_id")


for _name, _op, _method in (("union", "UNION", None), ("union_all", "UNION ALL", "union"), ("intersect", "INTERSECT", "intersect"), ("intersect_all", "INTERSECT ALL", "intersectAll"), ("except", "EXCEPT", "subtract"), ("except_all", "EXCEPT ALL", "exceptAll")):

    def _setop(spark, d, method=_method):
        a, b = table(spark, d, "customer").select(F.col("c_nationkey").alias("k")), table(spark, d, "supplier").select(F.col("s_nationkey").alias("k"))
        return a.union(b).distinct() if method is None else getattr(a, method)(b)

    query(f"setop_{_name}", f"SELECT c_nationkey AS k FROM customer {_op} SELECT s_nationkey FROM supplier")(_setop)


def _functions(name: str, source: str, sql: str, columns):
    def run(spark, d):
        return table(spark, d, source).select(*columns())

    query(name, f"SELECT {sql} FROM {source}")(run)


_functions("fn_string", "documents", "doc_id, upper(lang) || '-' || lpad(source, 8, '_') AS s, reverse(source) AS r, length(text)::INT AS n, levenshtein(source, lang)::INT AS lev", lambda: ["doc_id", F.concat_ws("-", F.upper("lang"), F.lpad("source", 8, "_")).alias("s"), F.reverse("source").alias("r"), F.length("text").alias("n"), F.levenshtein("source", "lang").alias("lev")])
_functions("fn_regex", "documents", "doc_id, regexp_extract(text, '([A-Z][a-z]+)', 1) AS first_cap, len(regexp_extract_all(text, '[0-9]+'))::INT AS n_numbers", lambda: ["doc_id", F.regexp_extract("text", "([A-Z][a-z]+)", 1).alias("first_cap"), F.regexp_count("text", F.lit("[0-9]+")).alias("n_numbers")])
_functions("fn_date", "events", "event_id, date_trunc('day', ts)::DATE AS day, extract(hour FROM ts)::INT AS h, date_diff('day', TIMESTAMP '2024-01-01', ts)::INT AS n", lambda: ["event_id", F.to_date("ts").alias("day"), F.hour("ts").alias("h"), F.datediff(F.to_date("ts"), F.lit("2024-01-01").cast("date")).alias("n")])
_functions("fn_math", "lineitem", "l_orderkey, l_linenumber, round(sqrt(l_quantity), 6) AS s, floor(l_quantity / 7)::BIGINT AS f, round(ln(l_quantity), 6) AS l", lambda: ["l_orderkey", "l_linenumber", F.round(F.sqrt("l_quantity"), 6).alias("s"), F.floor(F.col("l_quantity") / 7).alias("f"), F.round(F.log("l_quantity"), 6).alias("l")])
_functions("fn_array", "documents", "doc_id, len(string_split(text, ' '))::INT AS n, md5(array_to_string(list_sort(list_distinct(string_split(text, ' '))), ' ')) AS w", lambda: ["doc_id", F.size(F.split("text", " ")).alias("n"), F.md5(F.array_join(F.array_sort(F.array_distinct(F.split("text", " "))), " ").cast("binary")).alias("w")])
_functions("fn_map", "documents", "doc_id, 'source' AS k, source AS v", lambda: ["doc_id", F.explode(F.map_filter(F.create_map(F.lit("lang"), "lang", F.lit("source"), "source"), lambda k, v: k == "source")).alias("k", "v")])
_functions("fn_json", "events", "event_id, (props->>'$.k')::INT AS k", lambda: ["event_id", F.get_json_object("props", "$.k").cast("int").alias("k")])
_functions("fn_hash", "documents", "doc_id, md5(text) AS m, sha256(text) AS s", lambda: ["doc_id", F.md5("text").alias("m"), F.sha2("text", 256).alias("s")])
_functions("fn_url", "pages", "page_id, regexp_extract(url, '^([a-z]+)://', 1) AS scheme", lambda: ["page_id", F.parse_url("url", F.lit("PROTOCOL")).alias("scheme")])


@query("fn_variant")
def _variant(spark, d):
    return table(spark, d, "events").select("event_id", F.variant_get(F.parse_json("props"), "$.k", "int").alias("k"))


@query("subquery_scalar", "SELECT o_orderkey FROM orders WHERE o_totalprice > (SELECT avg(o_totalprice) * 1.8 FROM orders)")
def _scalar(spark, d):
    o = table(spark, d, "orders")
    return o.join(o.agg((F.avg("o_totalprice") * 1.8).alias("m")), F.col("o_totalprice") > F.col("m")).select("o_orderkey")


@query("subquery_exists", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderstatus = 'P')")
def _exists(spark, d):
    o, c = _orders(spark, d)
    return c.join(o.filter("o_orderstatus = 'P'"), F.col("o_custkey") == F.col("c_custkey"), "left_semi").select("c_custkey")


@query("cte_recursive", "WITH RECURSIVE m AS MATERIALIZED (SELECT month(o_orderdate)::INT AS k, count(*) AS c FROM orders GROUP BY 1), t AS (SELECT k AS n, c AS f FROM m WHERE k = 1 UNION ALL SELECT k, f + c FROM t JOIN m ON k = n + 1) SELECT n, f::BIGINT AS f FROM t")
def _recursive(spark, d):
    """Orders up to each month of the year, carried from month to month; the table is read once, the recursion walks its sums."""
    m = reliable(table(spark, d, "orders").groupBy(F.month("o_orderdate").alias("k")).agg(F.count("*").alias("c")))
    return spark.sql("WITH RECURSIVE t AS (SELECT k AS n, c AS f FROM {m} WHERE k = 1 UNION ALL SELECT k, f + c FROM t JOIN {m} ON k = n + 1) SELECT n, f FROM t", m=m)
