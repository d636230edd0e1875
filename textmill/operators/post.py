"""Post-training data: samples, annotation, filters, judges, arena, preference pairs, feedback.

Judges, annotators and generators are deterministic stand-ins: integer rules over the text with a hash term for taste.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..catalog import query, table
from ..functions.text import h28, ratio, sql_h28, sql_ratio, words
from ..plans.ranks import cut_points

_SQL_W = "list_filter(string_split_regex(lower(text), '[ \\t\\n\\r]+'), lambda x: x <> '')"
_SQL_PAIRS = """(SELECT conv_id, turn, text AS prompt, lead(text) OVER (PARTITION BY conv_id ORDER BY turn) AS response, lead(role) OVER (PARTITION BY conv_id ORDER BY turn) AS next_role, role FROM conversations)"""
#: An exchange's number is that of its dialog times this, plus its turn.
TURNS = 1 << 24
_SQL_QA = f"(SELECT conv_id * {TURNS} + turn AS pid, conv_id, turn, prompt, response FROM {_SQL_PAIRS} WHERE role = 'user' AND next_role = 'assistant')"


def samples(conv: DataFrame) -> DataFrame:
    """One row per dialog: ordered turns, its system prompt apart, and whether it is multi-turn."""
    g = conv.groupBy("conv_id").agg(F.array_sort(F.collect_list(F.struct("turn", "role", "text"))).alias("turns"))
    system = F.get(F.filter("turns", lambda t: t["role"] == "system"), 0)["text"]
    users = F.size(F.filter("turns", lambda t: t["role"] == "user"))
    return g.select("conv_id", F.filter("turns", lambda t: t["role"] != "system").alias("turns"), system.alias("system"), users.alias("n_user"), (users > 1).alias("multi_turn"))


@query("dialog_samples", "SELECT conv_id, count(*) FILTER (role <> 'system')::INT AS n_turns, max(text) FILTER (role = 'system') AS system, count(*) FILTER (role = 'user') > 1 AS multi_turn FROM conversations GROUP BY conv_id")
def _samples(spark, d):
    return samples(table(spark, d, "conversations")).select("conv_id", F.size("turns").alias("n_turns"), "system", "multi_turn")


@query("dialog_stats", "SELECT multi, count(*) AS n, round(avg(n_turns), 6) AS mean_turns, max(n_turns)::BIGINT AS most FROM (SELECT conv_id, count(*) FILTER (role = 'user') > 1 AS multi, count(*) AS n_turns FROM conversations GROUP BY conv_id) GROUP BY multi")
def _stats(spark, d):
    g = table(spark, d, "conversations").groupBy("conv_id").agg((F.count_if(F.col("role") == "user") > 1).alias("multi"), F.count("*").alias("n_turns"))
    return g.groupBy("multi").agg(F.count("*").alias("n"), F.round(F.avg("n_turns"), 6).alias("mean_turns"), F.max("n_turns").alias("most"))


def exchanges(conv: DataFrame) -> DataFrame:
    """pid, conv_id, turn, prompt, response of each user turn that an assistant answers."""
    w = Window.partitionBy("conv_id").orderBy("turn")
    p = conv.select("conv_id", "turn", "role", F.col("text").alias("prompt"), F.lead("text").over(w).alias("response"), F.lead("role").over(w).alias("next"))
    return p.filter("role = 'user' and next = 'assistant'").select((F.col("conv_id") * TURNS + F.col("turn")).alias("pid"), "conv_id", "turn", "prompt", "response")


_SQL_ANN = f"(SELECT pid, conv_id, turn, ({sql_h28('conv_id::VARCHAR')} % 11)::INT AS capability, ntile(3) OVER (ORDER BY len(string_split(prompt, ' ')), pid)::INT AS complexity, CASE WHEN contains(response, chr(10)) THEN 'lines' ELSE 'plain' END AS style, prompt, response FROM {_SQL_QA})"


def annotate(qa: DataFrame) -> DataFrame:
    """Capability (11 classes), complexity (terciles of prompt length) and style of each exchange. The terciles' ends are
    found by ranks over ranges; no task sees all exchanges."""
    n = F.size(F.split("prompt", " "))
    cuts = cut_points(qa.select(n.alias("n_"), "pid"), ["n_", "pid"], 3)
    complexity = 1 + F.size(F.filter("cuts", lambda c: c <= F.struct(n.alias("n_"), F.col("pid"))))
    capability = (h28(F.col("conv_id").cast("string")) % 11).cast("int")
    style = F.when(F.contains("response", F.lit("\n")), "lines").otherwise("plain")
    return qa.crossJoin(F.broadcast(cuts)).select(*qa.columns, capability.alias("capability"), complexity.alias("complexity"), style.alias("style"))  # cuts is one row


@query("sample_annotations", f"SELECT pid, capability, complexity, style FROM {_SQL_ANN}")
def _annotations(spark, d):
    return annotate(exchanges(table(spark, d, "conversations"))).select("pid", "capability", "complexity", "style")


def judge(text: Column, name: str, few: int, unique: float) -> Column:
    """Score 1-10: penalties for short, repetitive and unended answers and a hash term."""
    w = words(text)
    n = F.size(w)
    u = F.when(n > 0, F.size(F.array_distinct(w)) / n).otherwise(0.0)
    s = 10 - 3 * (n < few).cast("int") - 2 * (u < unique).cast("int") - (~text.rlike("[.!?]$")).cast("int") - h28(F.concat(F.lit(name), text)) % 5
    return F.greatest(F.lit(1), F.least(F.lit(10), s)).cast("int")


def sql_judge(text: str, name: str, few: int, unique: float) -> str:
    w = _SQL_W.replace("lower(text)", f"lower({text})")
    u = f"(CASE WHEN len({w}) > 0 THEN len(list_distinct({w}))::DOUBLE / len({w}) ELSE 0 END)"
    return f"greatest(1, least(10, 10 - 3 * (len({w}) < {few})::INT - 2 * ({u} < {unique})::INT - (NOT regexp_matches({text}, '[.!?]$'))::INT - {sql_h28(f"'{name}' || {text}")} % 5))::INT"


A, B = ("A", 5, 0.5), ("B", 10, 0.6)


@query("judge_scores", f"SELECT pid, {sql_judge('response', *A)} AS a, {sql_judge('response', *B)} AS b FROM {_SQL_QA}")
def _judged(spark, d):
    return exchanges(table(spark, d, "conversations")).select("pid", judge(F.col("response"), *A).alias("a"), judge(F.col("response"), *B).alias("b"))


def level1(qa: DataFrame) -> DataFrame:
    """Kept exchanges: a good score, or a fair one in a capability that has few samples."""
    s = annotate(qa).withColumn("score", judge(F.col("response"), *A))
    share = F.count("*").over(Window.partitionBy("capability"))
    return s.withColumn("n", share).filter((F.col("score") >= 8) | ((F.col("score") >= 6) & (F.col("n") < 20)))


_SQL_L1 = f"(SELECT * FROM (SELECT *, {sql_judge('response', *A)} AS score, count(*) OVER (PARTITION BY capability) AS n FROM {_SQL_ANN}) WHERE score >= 8 OR (score >= 6 AND n < 20))"
_SQL_L2 = f"(SELECT * FROM {_SQL_L1} WHERE length(response)::DOUBLE / length(prompt) BETWEEN 0.2 AND 20 AND capability NOT IN (3, 7))"
_SQL_L3 = f"(SELECT * FROM {_SQL_L2} WHERE NOT regexp_matches(lower(response), 'token|password|secret'))"


@query("level1_filter", f"SELECT pid, score FROM {_SQL_L1}")
def _l1(spark, d):
    return level1(exchanges(table(spark, d, "conversations"))).select("pid", "score")


def level2(df: DataFrame) -> DataFrame:
    """After translation: lengths out of proportion and task kinds that translate badly go."""
    return df.filter((F.length("response") / F.length("prompt")).between(0.2, 20) & ~F.col("capability").isin(3, 7))


def level3(df: DataFrame) -> DataFrame:
    """Answers against the policy's word list go."""
    return df.filter(~F.lower("response").rlike("token|password|secret"))


@query("level2_filter", f"SELECT pid FROM {_SQL_L2}")
def _l2(spark, d):
    return level2(level1(exchanges(table(spark, d, "conversations")))).select("pid")


@query("level3_filter", f"SELECT pid FROM {_SQL_L3}")
def _l3(spark, d):
    return level3(level2(level1(exchanges(table(spark, d, "conversations"))))).select("pid")


@query("filter_funnel", f"SELECT 'all' AS level, count(*) AS n FROM {_SQL_QA} UNION ALL SELECT 'level1', count(*) FROM {_SQL_L1} UNION ALL SELECT 'level2', count(*) FROM {_SQL_L2} UNION ALL SELECT 'level3', count(*) FROM {_SQL_L3}")
def funnel(spark, d):
    qa = exchanges(table(spark, d, "conversations"))
    one = level1(qa)
    out = None
    for name, df in (("all", qa), ("level1", one), ("level2", level2(one)), ("level3", level3(level2(one)))):
        n = df.agg(F.count("*").alias("n")).select(F.lit(name).alias("level"), "n")
        out = n if out is None else out.union(n)
    return out


#: Exchanges of a block in which answers are exchanged; blocks are by hash, as many as the table needs.
BLOCK = 64
_SQL_BLOCKS = f"(SELECT greatest(16, (count(*) + {BLOCK - 1}) // {BLOCK}) FROM {_SQL_QA})"

# Candidate answers of a prompt: its own and the three of other dialogs that come first in a hash order of the prompt.
_SQL_CAND = f"""(SELECT pid, prompt, rid, response FROM (SELECT p.pid, p.prompt, r.pid AS rid, r.response, row_number() OVER (PARTITION BY p.pid ORDER BY (p.pid <> r.pid)::INT, {sql_h28("p.pid::VARCHAR || '-' || r.pid::VARCHAR")}, r.pid) AS rn
  FROM {_SQL_QA} p JOIN {_SQL_QA} r ON {sql_h28('p.pid::VARCHAR')} % {_SQL_BLOCKS} = {sql_h28('r.pid::VARCHAR')} % {_SQL_BLOCKS} AND (p.pid = r.pid OR p.conv_id <> r.conv_id)) WHERE rn <= 4)"""


def in_blocks(qa: DataFrame) -> DataFrame:
    """qa with its hash block; blocks hold about BLOCK exchanges however many there are, so a join of blocks is linear."""
    return qa.withColumn("block", h28(F.col("pid").cast("string")) % max(16, -(-qa.count() // BLOCK)))


def generate(qa: DataFrame, k: int = 4) -> DataFrame:
    """k answers per prompt; other dialogs' answers stand for other models. Blocks by hash bound the comparison."""
    qa = in_blocks(qa)
    p = qa.select("pid", "conv_id", "prompt", "block")
    r = qa.select(F.col("pid").alias("rid"), F.col("conv_id").alias("rconv"), "response", "block")
    j = p.join(r, "block").filter((F.col("pid") == F.col("rid")) | (F.col("conv_id") != F.col("rconv")))
    order = Window.partitionBy("pid").orderBy((F.col("pid") != F.col("rid")).cast("int"), h28(F.concat_ws("-", "pid", "rid")), "rid")
    return j.withColumn("rn", F.row_number().over(order)).filter(F.col("rn") <= k).select("pid", "prompt", "rid", "response")


_SQL_SCORED = f"(SELECT *, {sql_judge('response', *A)} AS a, {sql_judge('response', *B)} AS b FROM {_SQL_CAND})"


def scored(spark, d) -> DataFrame:
    return generate(exchanges(table(spark, d, "conversations"))).withColumns({"a": judge(F.col("response"), *A), "b": judge(F.col("response"), *B)})


@query("arena_winner", f"WITH s AS MATERIALIZED {_SQL_SCORED}, w AS (SELECT x.pid, x.rid, any_value(x.response) AS response, count(*) FILTER (x.a > y.a + 1) AS wins FROM s x JOIN s y ON x.pid = y.pid AND x.rid <> y.rid GROUP BY x.pid, x.rid) SELECT pid, arg_max(rid, (wins, -length(response), -rid)) AS rid, max(wins) AS wins FROM w GROUP BY pid")
def arena(spark, d):
    """A beats B if it wins in both orders of showing, the first shown having one point more; then the shorter wins."""
    s = scored(spark, d).select("pid", "rid", "response", "a")
    o = s.select("pid", F.col("rid").alias("other"), F.col("a").alias("oa"))
    w = s.join(o, "pid").filter("rid <> other").groupBy("pid", "rid").agg(F.first("response").alias("response"), F.count_if(F.col("a") > F.col("oa") + 1).alias("wins"))
    return w.groupBy("pid").agg(F.max_by("rid", F.struct("wins", -F.length("response"), -F.col("rid"))).alias("rid"), F.max("wins").alias("wins"))


@query("sft_set", f"SELECT pid, rid FROM {_SQL_SCORED} WHERE a >= 8 AND b >= 8")
def sft_set(spark, d):
    return scored(spark, d).filter("a >= 8 and b >= 8").select("pid", "rid")


_SQL_PREF = f"""(WITH s AS MATERIALIZED (SELECT pid, rid, (a + b) / 2.0::DOUBLE AS s, response FROM {_SQL_SCORED}), c AS (SELECT pid, arg_max(rid, (s, -rid)) AS chosen, max(s) AS s_chosen FROM s WHERE s >= 8 GROUP BY pid), r AS (SELECT pid, arg_min(rid, (s, rid)) AS rejected, min(s) AS s_rejected FROM s WHERE s BETWEEN 2 AND 6 GROUP BY pid)
  SELECT pid, chosen, rejected, s_chosen, s_rejected FROM c JOIN r USING (pid) WHERE s_chosen - s_rejected >= 2)"""


@query("preference_pairs", f"SELECT * FROM {_SQL_PREF}")
def preference_pairs(spark, d):
    """Best answer at a mean of 8 or more against the worst between 2 and 6, at least 2 apart: one pass over a prompt."""
    m = (F.col("a") + F.col("b")) / 2.0
    good, bad = F.when(F.col("s") >= 8, F.struct("s", -F.col("rid"))), F.when(F.col("s").between(2, 6), F.struct("s", "rid"))
    g = scored(spark, d).select("pid", "rid", m.alias("s")).groupBy("pid").agg(F.max(good).alias("c"), F.min(bad).alias("r")).filter("c is not null and r is not null")
    return g.select("pid", (-F.col("c")["col2"]).alias("chosen"), F.col("r.rid").alias("rejected"), F.col("c.s").alias("s_chosen"), F.col("r.s").alias("s_rejected")).filter("s_chosen - s_rejected >= 2")


@query("dpo_chunks", f"SELECT pid, ((row_number() OVER (ORDER BY pid) - 1) // 20)::BIGINT AS chunk FROM {_SQL_PREF}")
def dpo_chunks(spark, d, size: int = 20):
    """Chunks after each of which the reference model would be refreshed; numbered by a prefix sum."""
    from ..plans.prefixsum import prefix_sum

    return prefix_sum(preference_pairs(spark, d).select("pid"), ["pid"], F.lit(1).cast("bigint"), "before").select("pid", F.floor(F.col("before") / size).alias("chunk"))


@query("preference_losses", f"SELECT pid, round(-ln(1 / (1 + exp(-0.1::DOUBLE * (s_chosen - s_rejected)))), 6) AS dpo, round(pow(0.1::DOUBLE * (s_chosen - s_rejected) - 0.5, 2), 6) AS ipo, round(1 - 1 / (1 + exp(-0.1::DOUBLE * (s_chosen - 7))), 6) AS kto, round(-ln(1 / (1 + exp(-(2.0::DOUBLE * (s_chosen - s_rejected) / 10 - 0.5)))), 6) AS simpo FROM {_SQL_PREF}")
def losses(spark, d):
    """Preference losses as expressions over margins; judge means stand for log-probability ratios."""
    m, c = F.col("s_chosen") - F.col("s_rejected"), F.col("s_chosen")
    sig = lambda x: 1 / (1 + F.exp(-x))
    return preference_pairs(spark, d).select("pid", F.round(-F.log(sig(0.1 * m)), 6).alias("dpo"), F.round(F.pow(0.1 * m - 0.5, 2), 6).alias("ipo"), F.round(1 - sig(0.1 * (c - 7)), 6).alias("kto"), F.round(-F.log(sig(2.0 * m / 10 - 0.5)), 6).alias("simpo"))


# Events as feedback: purchase is great (+1), click like (+1), error dislike (-1); props.k names prompt and reason.
_SQL_VOTE = "(SELECT event_id, ts, user_id, (props->>'$.k')::INT AS prompt, event_id % 2 AS side, CASE event_type WHEN 'purchase' THEN 1 WHEN 'click' THEN 1 WHEN 'error' THEN -1 END AS vote, event_type FROM events)"


def votes(ev: DataFrame) -> DataFrame:
    v = F.when(F.col("event_type").isin("purchase", "click"), 1).when(F.col("event_type") == "error", -1)
    return ev.select("event_id", "ts", "user_id", "event_type", F.get_json_object("props", "$.k").cast("int").alias("prompt"), (F.col("event_id") % 2).alias("side"), v.alias("vote"))


@query("judge_agreement", f"WITH s AS (SELECT prompt, coalesce(sum(vote) FILTER (side = 0), 0) - coalesce(sum(vote) FILTER (side = 1), 0) AS diff FROM {_SQL_VOTE} WHERE vote IS NOT NULL GROUP BY prompt) SELECT count(*) AS n, count(*) FILTER (diff < 0) AS disagree, count(*) FILTER (diff = 0) AS tied, {sql_ratio('count(*) FILTER (diff >= 0)', 'count(*)')} AS agreement FROM s")
def agreement(spark, d):
    """Sum of votes of the chosen (side 0) less that of the rejected answer; below zero is disagreement."""
    v = votes(table(spark, d, "events")).filter("vote is not null")
    s = v.groupBy("prompt").agg(F.sum(F.when(F.col("side") == 0, F.col("vote")).otherwise(-F.col("vote"))).alias("diff"))
    return s.agg(F.count("*").alias("n"), F.count_if(F.col("diff") < 0).alias("disagree"), F.count_if(F.col("diff") == 0).alias("tied"), ratio(F.count_if(F.col("diff") >= 0), F.count("*")).alias("agreement"))


_SQL_DAILY = "SELECT ts::DATE AS day, count(*) AS prompts, count(DISTINCT user_id) AS users, count(*) FILTER (event_type = 'error') AS dislikes, " + sql_ratio("count(*) FILTER (event_type = 'error')", "count(*)") + " AS dislike_rate FROM events GROUP BY 1"


@query("feedback_daily", _SQL_DAILY)
def feedback_daily(spark, d):
    g = table(spark, d, "events").groupBy(F.to_date("ts").alias("day"))
    bad = F.count_if(F.col("event_type") == "error")
    return g.agg(F.count("*").alias("prompts"), F.count_distinct("user_id").alias("users"), bad.alias("dislikes"), ratio(bad, F.count("*")).alias("dislike_rate"))


@query("dislike_reasons", f"SELECT (prompt % 8)::INT AS reason, count(*) AS n FROM {_SQL_VOTE} WHERE event_type = 'error' GROUP BY 1")
def dislike_reasons(spark, d):
    return votes(table(spark, d, "events")).filter("event_type = 'error'").groupBy((F.col("prompt") % 8).alias("reason")).agg(F.count("*").alias("n"))


@query("anneal_subset", f"SELECT pid, capability FROM (SELECT pid, capability, row_number() OVER (PARTITION BY capability ORDER BY score DESC, pid) AS rn FROM {_SQL_L3}) WHERE rn <= 3")
def anneal(spark, d, n: int = 3):
    rn = F.row_number().over(Window.partitionBy("capability").orderBy(F.desc("score"), "pid"))
    return level3(level2(level1(exchanges(table(spark, d, "conversations"))))).withColumn("rn", rn).filter(F.col("rn") <= n).select("pid", "capability")


@query("sft_stage_split", f"SELECT pid, CASE WHEN capability IN (0, 10) THEN 2 WHEN {sql_h28('pid::VARCHAR')} % 5 = 0 THEN 2 ELSE 1 END AS stage FROM {_SQL_L1}")
def stages(spark, d):
    """Stage 2 takes the value capabilities whole and a hash sample of the others."""
    return level1(exchanges(table(spark, d, "conversations"))).select("pid", F.when(F.col("capability").isin(0, 10), 2).when(h28(F.col("pid").cast("string")) % 5 == 0, 2).otherwise(1).alias("stage"))


@query("preference_triples", r"SELECT item_id, a AS neutral, a || ' ' || b AS positive, a || ' not ' || b AS negative FROM (SELECT item_id, split_part(text, ' ', 1) AS a, split_part(text, ' ', 2) AS b FROM benchmark)")
def triples(spark, d):
    """Neutral, positive and negative prompts from statements of two parts."""
    b = table(spark, d, "benchmark").select("item_id", F.split_part("text", F.lit(" "), F.lit(1)).alias("a"), F.split_part("text", F.lit(" "), F.lit(2)).alias("b"))
    return b.select("item_id", F.col("a").alias("neutral"), F.concat_ws(" ", "a", "b").alias("positive"), F.concat_ws(" not ", "a", "b").alias("negative"))


@query("task_diacritize", "SELECT item_id, translate(lower(text), 'àâäáãåçéèêëíìîïñóòôöõúùûüýÿ', 'aaaaaaceeeeiiiinooooouuuuyy') AS prompt, lower(text) AS answer FROM benchmark")
def diacritize(spark, d):
    """Marks are taken away; the answer puts them back."""
    t = F.lower("text")
    return table(spark, d, "benchmark").select("item_id", F.translate(t, "àâäáãåçéèêëíìîïñóòôöõúùûüýÿ", "aaaaaaceeeeiiiinooooouuuuyy").alias("prompt"), t.alias("answer"))


@query("spell_error_rate", f"WITH f AS (SELECT lang, doc_id, unnest({_SQL_W}) AS word FROM documents), l AS (SELECT lang, word FROM f GROUP BY ALL HAVING count(DISTINCT doc_id) >= 3) SELECT doc_id, {sql_ratio('count(*) FILTER (l.word IS NULL)', 'count(*)')} AS rate FROM f LEFT JOIN l ON f.lang = l.lang AND f.word = l.word GROUP BY doc_id")
def spell_rate(spark, d):
    """Share of words that fewer than three documents of the language have."""
    f = table(spark, d, "documents").select("lang", "doc_id", F.explode(words("text")).alias("word"))
    known = f.distinct().groupBy("lang", "word").agg(F.count("*").alias("df")).filter("df >= 3").select("lang", "word", F.lit(1).alias("ok"))
    return f.join(known, ["lang", "word"], "left").groupBy("doc_id").agg(ratio(F.count_if(F.col("ok").isNull()), F.count("*")).alias("rate"))
