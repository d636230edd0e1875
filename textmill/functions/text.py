"""Text expressions that Spark and the oracle compute alike, and script profiles."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Names of the same expressions in the oracle's SQL.
SQL_WORDS = "list_filter(string_split_regex(lower(text), '[ \\t\\n\\r]+'), lambda x: x <> '')"
SQL_RAW_WORDS = "list_filter(string_split_regex(text, '[ \\t\\n\\r]+'), lambda x: x <> '')"
SQL_LINES = "list_filter(string_split(text, chr(10)), lambda x: regexp_matches(x, '[^ \\t\\r]'))"


def words(text: Column | str, lower: bool = True) -> Column:
    """Non-empty pieces between runs of blanks, tabs and line breaks."""
    c = F.col(text) if isinstance(text, str) else text
    return F.filter(F.split(F.lower(c) if lower else c, "[ \t\n\r]+"), lambda x: x != "")


GAPS = str.maketrans("\t\n\r", "   ")


def words_of(text: str | None) -> list[str]:
    """words() of one text, in Python."""
    return [w for w in (text or "").lower().translate(GAPS).split(" ") if w]


def lines(text: Column | str) -> Column:
    """Lines that are not blank."""
    return F.filter(F.split(text, "\n"), lambda x: x.rlike("[^ \t\r]"))


def h28(x: Column) -> Column:
    """A 28-bit number from MD5, the same in every engine."""
    return F.conv(F.substring(F.md5(x.cast("binary")), 1, 7), 16, 10).cast("bigint")


def sql_h28(x: str) -> str:
    return f"('0x' || substr(md5({x}), 1, 7))::BIGINT"


def grams(tokens: Column, n: int, sep: str = " ") -> Column:
    """Runs of n tokens as strings; fewer tokens make one run, none make none."""
    few = F.when(F.size(tokens) > 0, F.array(F.array_join(tokens, sep))).otherwise(F.array().cast("array<string>"))
    runs = F.transform(F.sequence(F.lit(1), F.size(tokens) - (n - 1)), lambda i: F.array_join(F.slice(tokens, i, n), sep))
    return F.when(F.size(tokens) >= n, runs).otherwise(few)


def sql_grams(tokens: str, n: int) -> str:
    return (
        f"CASE WHEN len({tokens}) >= {n} THEN list_transform(range(1, len({tokens}) - {n} + 2), lambda i: array_to_string({tokens}[i:i+{n - 1}], ' ')) "
        f"WHEN len({tokens}) > 0 THEN [array_to_string({tokens}, ' ')] ELSE [] END"
    )


def ratio(a: Column, b: Column) -> Column:
    """a / b to 6 places, 0 where b is 0."""
    return F.round(F.when(b > 0, a.cast("double") / b.cast("double")).otherwise(F.lit(0.0)), 6)


def sql_ratio(a: str, b: str) -> str:
    return f"round(CASE WHEN {b} > 0 THEN ({a})::DOUBLE / ({b})::DOUBLE ELSE 0.0 END, 6)"


@dataclass(frozen=True)
class ScriptProfile:
    """What a rule needs to know of a script: all expressions take it as a parameter, none names a language."""

    letters: str  # a character class body, its target letters
    terminators: str
    stop_words: tuple[str, ...] = ()
    bullets: str = "\\-*•|"
    marks: str = "\\p{M}"
    fold: tuple[tuple[str, str], ...] = field(default_factory=tuple)  # (characters, replacements) of equal length


LATIN = ScriptProfile(
    letters="A-Za-zÀ-ÖØ-öø-ɏ",
    terminators=".!?…",
    stop_words=("the", "of", "and", "to", "is", "in", "for", "as", "by", "le", "la", "de", "et", "der", "die", "und", "el", "que", "en", "un"),
    fold=(("àâäáãåçéèêëíìîïñóòôöõúùûüýÿ", "aaaaaaceeeeiiiinooooouuuuyy"),),
)
#: Right-to-left punctuation, Arabic-Indic and Persian digits, letters of neighbouring languages, decorated forms.
ARABIC = ScriptProfile(
    letters="\u0621-\u064a\u0671-\u06d3",
    terminators=".!?…\u061f\u06d4",
    stop_words=("في", "من", "على", "إلى", "عن", "أن", "هذا", "التي", "الذي", "مع"),
    marks="\\p{M}\u0640",
    fold=(("\u0660\u0661\u0662\u0663\u0664\u0665\u0666\u0667\u0668\u0669", "0123456789"), ("\u06f0\u06f1\u06f2\u06f3\u06f4\u06f5\u06f6\u06f7\u06f8\u06f9", "0123456789"), ("\u06a9\u06cc\u06c1\u0622\u0623\u0625", "\u0643\u064a\u0647\u0627\u0627\u0627")),
)


def normalize_script(text: Column, profile: ScriptProfile, strip_marks: bool = True) -> Column:
    """Lower case, folded letters and digits, and no combining marks or elongation."""
    out = F.lower(text)
    for a, b in profile.fold:
        out = F.translate(out, a, b)
    return F.regexp_replace(out, f"[{profile.marks}]", "") if strip_marks else out
