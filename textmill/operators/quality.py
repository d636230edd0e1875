"""Syntactic quality signals, histogram calibration, rule filters, baselines and their comparison."""

from __future__ import annotations

import math
import re
import unicodedata
from collections import Counter
from collections.abc import Iterator, Mapping

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..catalog import query, table
from ..functions.text import ARABIC, GAPS, LATIN, SQL_LINES, SQL_RAW_WORDS, SQL_WORDS, ScriptProfile, ratio, sql_ratio
from ..plans.spread import spread

SIGNALS = (
    "n_words", "n_sentences", "n_lines", "mean_word_len", "frac_unique_words", "unigram_entropy", "symbol_word_ratio", "punct_word_ratio", "special_char_frac", "digit_frac",
    "frac_words_no_letter", "frac_upper_words", "stopword_frac", "frac_lines_ellipsis", "frac_lines_terminal", "frac_lines_bullet", "mean_line_words", "frac_dup_lines", "code_marks", "target_script_frac",
)
#: Signals that lie in [0, 1] and are binned as they are.
FRACTIONS = tuple(s for s in SIGNALS if "frac" in s)


_CLASSES: list[np.ndarray] = []
_LETTER, _DIGIT, _PUNCTUATION, _PLAIN = 1, 2, 4, 8


def _classes() -> np.ndarray:
    """For each code point: letter, decimal digit, punctuation, and what isn't special (letters, marks, numbers, blanks)."""
    if not _CLASSES:
        kinds = [unicodedata.category(chr(c)) for c in range(0x110000)]
        bits = {k: _LETTER * (k[0] == "L") + _DIGIT * (k == "Nd") + _PUNCTUATION * (k[0] == "P") + _PLAIN * (k[0] in "LMN") for k in set(kinds)}
        table = np.array([bits[k] for k in kinds], np.uint8)
        table[[9, 10, 13, 32]] |= _PLAIN
        _CLASSES.append(table)
    return _CLASSES[0]


def _counted(profile: ScriptProfile):
    """Numerators and denominators of all signals, over Arrow batches: characters are counted by class for a batch at a
    time, words by type, so that what is asked of a word is asked once for each batch."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        stop, terminal = frozenset(profile.stop_words), re.compile(f"[{profile.terminators}]+")
        target, bullet = re.compile(f"[{profile.letters}]"), re.compile(f"[ \t]*[{profile.bullets}]")
        ends = tuple(profile.terminators)
        table = _classes()
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                texts = [t or "" for t in part.column("t").to_pylist()]
                edges = np.cumsum([0] + [len(t) for t in texts])
                kinds = table[np.frombuffer("".join(texts).encode("utf-32-le"), "<u4")]

                def per_text(bit: int) -> list[int]:
                    upto = np.concatenate([[0], np.cumsum(kinds & bit != 0)])  # noqa: B023
                    return (upto[edges[1:]] - upto[edges[:-1]]).tolist()  # noqa: B023

                known: dict[str, tuple[bool, bool]] = {}
                rows = []
                for t, letters, digits, marks, plain in zip(texts, *(per_text(b) for b in (_LETTER, _DIGIT, _PUNCTUATION, _PLAIN))):
                    w = [x for x in t.translate(GAPS).split(" ") if x]
                    low = t.lower()
                    lw = Counter(x for x in low.translate(GAPS).split(" ") if x)
                    lines_ = [x for x in t.split("\n") if x.strip(" \t\r")]
                    stripped = [x.rstrip(" \t\r") for x in lines_]
                    n, m = len(w), len(lines_)
                    bare = upper = 0
                    for x, c in Counter(w).items():
                        if x not in known:
                            known[x] = (not any(table[ord(y)] & _LETTER for y in x), x == x.upper() != x.lower())
                        bare, upper = bare + c * known[x][0], upper + c * known[x][1]
                    entropy = math.log(n) - sum(c * math.log(c) for c in lw.values() if c > 1) / n if n else 0.0
                    rows.append((
                        n, max(len(terminal.findall(t)), int(n > 0)), m, sum(map(len, w)), len(lw), entropy, t.count("#") + t.count("...") + t.count("…") + t.count("•"), marks, len(t) - plain, digits, bare, upper,
                        sum(lw[x] for x in stop if x in lw), sum(x.endswith(("...", "…")) for x in stripped), sum(x.endswith(ends) for x in stripped), sum(bullet.match(x) is not None for x in lines_), m - len(set(lines_)),
                        t.count("{") + low.count("javascript") + low.count("lorem ipsum"), len(target.findall(t)), len(t), letters,
                    ))
                cols = [part.column(0), *(pa.array(c, pa.float64()) for c in zip(*rows))]
                yield pa.RecordBatch.from_arrays(cols, names=[batch.schema.names[0], *_COUNTS])

    return run


_COUNTS = ("n", "sentences", "m", "word_chars", "distinct", "entropy", "symbols", "marks", "special", "digits", "bare", "upper", "stops", "ellipses", "terminals", "bullets", "repeats", "codes", "targets", "chars", "letters")


def signals(df: DataFrame, profile: ScriptProfile = LATIN, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """All 20 signals in one scan, without a shuffle, counted in Arrow batches: lambdas over arrays of words, interpreted
    for each word, take ten times as long.

    An empty or null text has 0 in every signal. Characters are code points. A null id stays; repeated rows stay.
    """
    c = spread(df.select(id_col, F.col(text).alias("t"))).mapInArrow(_counted(profile), f"{id_col} {df.schema[id_col].dataType.simpleString()}, " + ", ".join(f"{x} double" for x in _COUNTS))
    of = lambda a, b, name: ratio(F.col(a), F.col(b)).alias(name)
    return c.select(
        id_col,
        F.col("n").alias("n_words"),
        F.col("sentences").alias("n_sentences"),
        F.col("m").alias("n_lines"),
        of("word_chars", "n", "mean_word_len"),
        of("distinct", "n", "frac_unique_words"),
        F.round("entropy", 6).alias("unigram_entropy"),
        of("symbols", "n", "symbol_word_ratio"),
        of("marks", "n", "punct_word_ratio"),
        of("special", "chars", "special_char_frac"),
        of("digits", "chars", "digit_frac"),
        of("bare", "n", "frac_words_no_letter"),
        of("upper", "n", "frac_upper_words"),
        of("stops", "n", "stopword_frac"),
        of("ellipses", "m", "frac_lines_ellipsis"),
        of("terminals", "m", "frac_lines_terminal"),
        of("bullets", "m", "frac_lines_bullet"),
        of("n", "m", "mean_line_words"),
        F.round(F.when(F.col("m") > 0, 1 - (F.col("m") - F.col("repeats")) / F.col("m")).otherwise(F.lit(0.0)), 6).alias("frac_dup_lines"),
        F.col("codes").alias("code_marks"),
        of("targets", "letters", "target_script_frac"),
    )


def sql_signals(profile: ScriptProfile = LATIN) -> str:
    n, m, c = "len(w)", "len(l)", "length(t)"
    count = lambda p: f"len(regexp_extract_all(t, '{p}'))"
    stop = "[" + ", ".join(f"'{w}'" for w in profile.stop_words) + "]"
    return f"""SELECT doc_id, {n}::DOUBLE AS n_words, greatest({count(f'[{profile.terminators}]+')}, CASE WHEN {n} > 0 THEN 1 ELSE 0 END)::DOUBLE AS n_sentences, {m}::DOUBLE AS n_lines,
    {sql_ratio("length(array_to_string(w, ''))", n)} AS mean_word_len, {sql_ratio("len(list_distinct(lw))", n)} AS frac_unique_words,
    round(CASE WHEN {n} > 0 THEN list_aggregate(lw, 'entropy') * ln(2) ELSE 0.0 END, 6) AS unigram_entropy,
    {sql_ratio(count("#|[.][.][.]|…|•"), n)} AS symbol_word_ratio, {sql_ratio(count(chr(92) + "p{P}"), n)} AS punct_word_ratio,
    {sql_ratio(count("[^" + chr(92) + "p{L}" + chr(92) + "p{M}" + chr(92) + "p{N} " + chr(92) + "t" + chr(92) + "n" + chr(92) + "r]"), c)} AS special_char_frac, {sql_ratio(count(chr(92) + "p{Nd}"), c)} AS digit_frac,
    {sql_ratio("len(list_filter(w, lambda x: NOT regexp_matches(x, '" + chr(92) + "p{L}')))", n)} AS frac_words_no_letter,
    {sql_ratio("len(list_filter(w, lambda x: x = upper(x) AND x <> lower(x)))", n)} AS frac_upper_words,
    {sql_ratio(f"len(list_filter(lw, lambda x: list_contains({stop}, x)))", n)} AS stopword_frac,
    {sql_ratio("len(list_filter(l, lambda x: regexp_matches(x, '([.][.][.]|…)[ " + chr(92) + "t" + chr(92) + "r]*$')))", m)} AS frac_lines_ellipsis,
    {sql_ratio(f"len(list_filter(l, lambda x: regexp_matches(x, '[{profile.terminators}][ " + chr(92) + "t" + chr(92) + "r]*$')))", m)} AS frac_lines_terminal,
    {sql_ratio(f"len(list_filter(l, lambda x: regexp_matches(x, '^[ " + chr(92) + f"t]*[{profile.bullets}]')))", m)} AS frac_lines_bullet,
    {sql_ratio(n, m)} AS mean_line_words, round(CASE WHEN {m} > 0 THEN 1 - len(list_distinct(l))::DOUBLE / {m} ELSE 0.0 END, 6) AS frac_dup_lines,
    {count("(?i)" + chr(92) + "{|javascript|lorem ipsum")}::DOUBLE AS code_marks, {sql_ratio(count(f"[{profile.letters}]"), count(chr(92) + "p{L}"))} AS target_script_frac
    FROM (SELECT doc_id, text AS t, {SQL_RAW_WORDS} AS w, {SQL_WORDS} AS lw, {SQL_LINES} AS l FROM documents)"""


@query("quality_signals", sql_signals())
def _signals(spark, d):
    return signals(table(spark, d, "documents"))


@query("signals_uniform_profile", f"SELECT doc_id, target_script_frac, stopword_frac, n_sentences FROM ({sql_signals(ARABIC)})")
def _uniform(spark, d):
    """Signals under a profile of another script: what a rule set that ignores the language sees."""
    return signals(table(spark, d, "documents"), ARABIC).select("doc_id", "target_script_frac", "stopword_frac", "n_sentences")


def histogram(sig: DataFrame, names: tuple[str, ...] = FRACTIONS, id_col: str = "doc_id") -> DataFrame:
    """(signal, bin, n): ten fixed bins of 0.1, 1.0 in the last; all signals in one aggregation of few groups."""
    return unpivoted(sig, names, id_col).groupBy("signal", "bin").agg(F.count("*").alias("n"))


def unpivoted(sig: DataFrame, names: tuple[str, ...], id_col: str = "doc_id") -> DataFrame:
    long = sig.unpivot([id_col], list(names), "signal", "value")
    return long.withColumn("bin", F.greatest(F.lit(0), F.least(F.lit(9), F.floor(F.round(F.col("value") * 10, 6)))).cast("int"))


_SQL_LONG = f"""(SELECT doc_id, signal, value, greatest(0, least(9, floor(round(value * 10, 6))))::INT AS bin FROM (UNPIVOT (SELECT doc_id, {', '.join(FRACTIONS)} FROM ({sql_signals()})) ON {', '.join(FRACTIONS)} INTO NAME signal VALUE value))"""


@query("signal_histogram", f"SELECT signal, bin, count(*) AS n FROM {_SQL_LONG} GROUP BY ALL")
def _histogram(spark, d):
    return histogram(signals(table(spark, d, "documents")))


def rescaled(sig: DataFrame, names: tuple[str, ...], kind: str = "minmax") -> DataFrame:
    """Signals that count are brought to [0, 1]: between least and greatest, or by logarithms."""
    f = (lambda c: F.log1p(c)) if kind == "log" else (lambda c: c)
    ends = sig.agg(*[x for c in names for x in (F.min(f(F.col(c))).alias(f"lo_{c}"), F.max(f(F.col(c))).alias(f"hi_{c}"))])
    scaled = [F.round(F.when(F.col(f"hi_{c}") > F.col(f"lo_{c}"), (f(F.col(c)) - F.col(f"lo_{c}")) / (F.col(f"hi_{c}") - F.col(f"lo_{c}"))).otherwise(0.0), 6).alias(c) for c in names]
    return sig.crossJoin(F.broadcast(ends)).select("doc_id", *scaled)  # ends is one row


@query(
    "signal_histogram_scaled",
    f"""WITH s AS ({sql_signals()}), e AS (SELECT min(ln(1 + n_words)) AS a, max(ln(1 + n_words)) AS b, min(ln(1 + n_lines)) AS c, max(ln(1 + n_lines)) AS d FROM s),
    l AS (SELECT 'n_words' AS signal, round((ln(1 + n_words) - a) / (b - a), 6) AS v FROM s, e UNION ALL SELECT 'n_lines', round((ln(1 + n_lines) - c) / (d - c), 6) FROM s, e)
    SELECT signal, greatest(0, least(9, floor(round(v * 10, 6))))::INT AS bin, count(*) AS n FROM l GROUP BY ALL""",
)
def _scaled(spark, d):
    return histogram(rescaled(signals(table(spark, d, "documents")), ("n_words", "n_lines"), "log"), ("n_words", "n_lines"))


def sample_bins(sig: DataFrame, names: tuple[str, ...] = FRACTIONS, k: int = 100, seed: str = "s") -> DataFrame:
    """k records of each bin in the order of a seeded hash: each task keeps at most k a bin before the shuffle."""
    order = Window.partitionBy("signal", "bin").orderBy(F.md5(F.concat(F.lit(seed), F.col("doc_id").cast("string"))), "doc_id")
    return unpivoted(sig, names).withColumn("rn", F.row_number().over(order)).filter(F.col("rn") <= k)


_SQL_SAMPLE = f"(SELECT * FROM {_SQL_LONG} QUALIFY row_number() OVER (PARTITION BY signal, bin ORDER BY md5('s' || doc_id::VARCHAR), doc_id) <= 100)"


@query("bin_samples", f"SELECT signal, bin, doc_id FROM {_SQL_SAMPLE}")
def _samples(spark, d):
    return sample_bins(signals(table(spark, d, "documents"))).select("signal", "bin", "doc_id")


def cutoffs(sample: DataFrame, labels: DataFrame, tau: float = 0.5) -> DataFrame:
    """(signal, low_cutoff, high_cutoff): the sample's bins from either end that are bad by tau or more are cut off.

    The labels stand for the inspection of samples by people. A side is cut up to the first bin that is good.
    """
    share = sample.join(labels.select("doc_id", "quality"), "doc_id").groupBy("signal", "bin").agg((F.avg(1 - F.col("quality")) < tau).alias("good"))
    return share.groupBy("signal").agg(F.round(F.min(F.when(F.col("good"), F.col("bin"))) / 10, 1).alias("low_cutoff"), F.round((F.max(F.when(F.col("good"), F.col("bin"))) + 1) / 10, 1).alias("high_cutoff"))


@query(
    "calibrated_cutoffs",
    f"""WITH b AS (SELECT signal, bin, avg(1 - quality) < 0.5 AS good FROM {_SQL_SAMPLE} JOIN labels USING (doc_id) GROUP BY ALL)
    SELECT signal, round(min(bin) FILTER (good) / 10.0::DOUBLE, 1) AS low_cutoff, round((max(bin) FILTER (good) + 1) / 10.0::DOUBLE, 1) AS high_cutoff FROM b GROUP BY ALL""",
)
def _cutoffs(spark, d):
    return cutoffs(sample_bins(signals(table(spark, d, "documents"))), table(spark, d, "labels"))


#: Signal -> (least, greatest) that a document may have; None is open.
RULES: Mapping[str, tuple[float | None, float | None]] = {
    "n_words": (10, None), "frac_unique_words": (0.2, None), "special_char_frac": (None, 0.1), "frac_words_no_letter": (None, 0.3),
    "frac_upper_words": (None, 0.5), "frac_dup_lines": (None, 0.5), "target_script_frac": (0.5, None),
}
#: The fixed recipe of an earlier model: only the share of special characters.
FIXED_RECIPE: Mapping[str, tuple[float | None, float | None]] = {"special_char_frac": (None, 0.2)}


def reasons(rules: Mapping[str, tuple[float | None, float | None]]) -> Column:
    """Array of the broken rules of a row of signals; empty for a row to keep."""
    tests = [F.when((F.col(c) < lo) if lo is not None else F.lit(False), F.lit(f"{c}<")) for c, (lo, _) in rules.items()]
    tests += [F.when((F.col(c) > hi) if hi is not None else F.lit(False), F.lit(f"{c}>")) for c, (_, hi) in rules.items()]
    return F.array_compact(F.array(*tests))


def sql_reasons(rules: Mapping[str, tuple[float | None, float | None]]) -> str:
    t = [f"CASE WHEN {c} < {lo} THEN '{c}<' END" for c, (lo, _) in rules.items() if lo is not None] + [f"CASE WHEN {c} > {hi} THEN '{c}>' END" for c, (_, hi) in rules.items() if hi is not None]
    return f"list_filter([{', '.join(t)}], lambda x: x IS NOT NULL)"


def apply_rules(sig: DataFrame, rules=RULES) -> tuple[DataFrame, DataFrame]:
    """(rows kept, audit of the rows dropped with their reasons)."""
    with_reasons = sig.withColumn("reasons", reasons(rules))
    return with_reasons.filter(F.size("reasons") == 0).drop("reasons"), with_reasons.filter(F.size("reasons") > 0).select("doc_id", "reasons")


_SQL_RULED = f"(SELECT *, {sql_reasons(RULES)} AS reasons FROM ({sql_signals()}))"


@query("rule_filter", f"SELECT doc_id FROM {_SQL_RULED} WHERE len(reasons) = 0")
def _rule_filter(spark, d):
    return apply_rules(signals(table(spark, d, "documents")))[0].select("doc_id")


@query("rule_drop_reasons", f"SELECT reason, count(*) AS n FROM (SELECT unnest(reasons) AS reason FROM {_SQL_RULED}) GROUP BY reason")
def _rule_reasons(spark, d):
    return apply_rules(signals(table(spark, d, "documents")))[1].select(F.explode("reasons").alias("reason")).groupBy("reason").agg(F.count("*").alias("n"))


@query("min_script_filter", f"SELECT doc_id FROM ({sql_signals()}) WHERE target_script_frac >= 0.5")
def _min_script(spark, d):
    return signals(table(spark, d, "documents")).filter("target_script_frac >= 0.5").select("doc_id")


@query("baseline_fixed_cutoffs", f"SELECT doc_id FROM ({sql_signals()}) WHERE special_char_frac <= 0.2")
def _fixed(spark, d):
    return apply_rules(signals(table(spark, d, "documents")), FIXED_RECIPE)[0].select("doc_id")


def paragraph_rule(df: DataFrame, n: int = 3, chars: int = 200) -> DataFrame:
    """A web rule made for another language: n lines of `chars` characters or more."""
    return df.filter(F.size(F.filter(F.split("text", "\n"), lambda x: F.length(x) >= chars)) >= n)


_SQL_PARAGRAPH = "len(list_filter(string_split(text, chr(10)), lambda x: length(x) >= 200)) >= 3"


@query("baseline_paragraph_rule", f"SELECT doc_id FROM documents WHERE {_SQL_PARAGRAPH}")
def _paragraph(spark, d):
    return paragraph_rule(table(spark, d, "documents")).select("doc_id")


@query(
    "recipe_ablation",
    f"""WITH f AS (SELECT doc_id, len(reasons) = 0 AS own, special_char_frac <= 0.2 AS fixed, para FROM {_SQL_RULED} JOIN (SELECT doc_id, {_SQL_PARAGRAPH} AS para FROM documents) USING (doc_id)),
    l AS (SELECT 'own_rules' AS recipe, doc_id, own AS kept FROM f UNION ALL SELECT 'fixed_cutoffs', doc_id, fixed FROM f UNION ALL SELECT 'paragraph_rule', doc_id, para FROM f)
    SELECT recipe, count(*) AS n, sum(kept::INT)::BIGINT AS n_kept, sum((kept AND quality = 1)::INT)::BIGINT AS good_kept, sum((kept AND quality = 0)::INT)::BIGINT AS bad_kept,
    {sql_ratio("sum((kept AND quality = 1)::INT)", "sum((kept AND quality IS NOT NULL)::INT)")} AS precision, {sql_ratio("sum((kept AND quality = 1)::INT)", "sum((quality = 1)::INT)")} AS recall,
    {sql_ratio("sum((NOT kept AND quality = 0)::INT)", "sum((quality = 0)::INT)")} AS bad_dropped FROM l LEFT JOIN labels USING (doc_id) GROUP BY recipe""",
)
def recipe_ablation(spark, d):
    """Retention and agreement with labels of three recipes; each recipe is one flag, all are summed in one pass."""
    docs = table(spark, d, "documents")
    sig = signals(docs).select("doc_id", (F.size(reasons(RULES)) == 0).alias("own_rules"), (F.size(reasons(FIXED_RECIPE)) == 0).alias("fixed_cutoffs"))
    para = docs.select("doc_id", (F.size(F.filter(F.split("text", "\n"), lambda x: F.length(x) >= 200)) >= 3).alias("paragraph_rule"))
    flags = sig.join(para, "doc_id").unpivot(["doc_id"], ["own_rules", "fixed_cutoffs", "paragraph_rule"], "recipe", "kept").join(table(spark, d, "labels").select("doc_id", "quality"), "doc_id", "left")
    n = lambda c: F.coalesce(F.sum(c.cast("bigint")), F.lit(0))
    k, q = F.col("kept"), F.col("quality")
    g = flags.groupBy("recipe").agg(F.count("*").alias("n"), n(k).alias("n_kept"), n(k & (q == 1)).alias("good_kept"), n(k & (q == 0)).alias("bad_kept"), n(~k & (q == 0)).alias("bd"), n(q == 1).alias("g"), n(q == 0).alias("b"))
    good, bad = F.col("good_kept"), F.col("bad_kept")
    return g.select("recipe", "n", "n_kept", "good_kept", "bad_kept", ratio(good, good + bad).alias("precision"), ratio(good, F.col("g")).alias("recall"), ratio(F.col("bd"), F.col("b")).alias("bad_dropped"))
