"""Document quality rules: repetition and length rules, and distance to a language's reference distributions."""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import common

#: Fixed values of the base rules: symbols, window of repeated words, least words, most repeated words in percent.
SYMBOLS, WINDOW, LEAST_WORDS, MOST_REPEATED = b"#*$%&|<>", 5, 10, 20
#: Words in a reference; words below which no divergence is judged; distances (square root of the base-2 divergence)
#: above which a document fails.
TOP_WORDS, GUARD_WORDS, MOST_CLASS, MOST_WORD = 100, 50, 0.30, 0.50

_CLASSES = ["lower", "upper", "digit", "blank", "newline", "stop", "dash", "quote", "mark", "symbol", "other", "beyond_ascii", ""]


def _class_table() -> np.ndarray:
    t = np.full(256, _CLASSES.index("other"), np.int64)
    for name, chars in {"lower": bytes(range(97, 123)), "upper": bytes(range(65, 91)), "digit": b"0123456789", "blank": b" \t", "newline": b"\n\r", "stop": b".,;:", "dash": b"-_", "quote": b"'\"`()", "mark": b"!?", "symbol": b"#*$%&|<>@=+/\\^~{}[]"}.items():
        t[list(chars)] = _CLASSES.index(name)
    t[128:192] = _CLASSES.index("")  # a character counts by its first byte
    t[192:] = _CLASSES.index("beyond_ascii")
    return t


_TABLE = _class_table()
_IS_SYMBOL = np.zeros(256, bool)
_IS_SYMBOL[list(SYMBOLS)] = True


def repeated_words(w: common.Words, size: int = WINDOW) -> int:
    """Words in windows of `size` words found twice or more in the text."""
    n = len(w.hashes)
    if n <= size:
        return 0
    at = np.arange(n - size + 1)
    names = w.name(at, at + size)
    order = np.argsort(names)
    same = names[order][1:] == names[order][:-1]
    twice = np.zeros(len(names), bool)
    twice[order[1:][same]] = True
    twice[order[:-1][same]] = True
    cover = np.zeros(n + 1, np.int64)
    np.add.at(cover, np.flatnonzero(twice), 1)
    np.add.at(cover, np.flatnonzero(twice) + size, -1)
    return int((np.cumsum(cover[:-1]) > 0).sum())


def base_counts(data: bytes) -> tuple[int, int, int, int, int]:
    """n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words of a text's UTF-8 bytes."""
    w, b = common.Words(data), np.frombuffer(data, np.uint8)
    chars = int(((b & 0xC0) != 0x80).sum() - common.IS_SPACE[b].sum())
    lines, seen, dup = data.split(b"\n"), set(), 0
    for line in lines:
        if line in seen:
            dup += 1
        elif line.split(None, 1):
            seen.add(line)
    return len(w.hashes), chars, int(_IS_SYMBOL[b].sum()), dup, repeated_words(w)


def char_classes(data: bytes) -> np.ndarray:
    return np.bincount(_TABLE[np.frombuffer(data, np.uint8)], minlength=len(_CLASSES))[:-1]


def js_distance(p: np.ndarray, q: np.ndarray) -> float:
    """Square root of the base-2 Jensen-Shannon divergence of two histograms; 0 for an empty one."""
    if not p.sum() or not q.sum():
        return 0.0
    p, q = p / p.sum(), q / q.sum()
    m = (p + q) / 2
    with np.errstate(divide="ignore", invalid="ignore"):
        d = np.where(p > 0, p * np.log2(p / m), 0).sum() + np.where(q > 0, q * np.log2(q / m), 0).sum()
    return float(max(d / 2, 0) ** 0.5)


_COUNTS = pa.schema([("lang", pa.string()), ("kind", pa.string()), ("item", pa.binary()), ("n", pa.int64())])


def _counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    words: dict[str | None, Counter] = {}
    classes: dict[str | None, np.ndarray] = {}

    def out() -> pa.RecordBatch:
        rows = [(lang, "word", k, n) for lang, c in words.items() for k, n in c.items()]
        rows += [(lang, "class", name.encode(), int(n)) for lang, c in classes.items() for name, n in zip(_CLASSES, c) if n]
        words.clear()
        classes.clear()
        return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(list(zip(*rows)) or [()] * 4, _COUNTS)], schema=_COUNTS)

    for batch in common.pieces(batches):
        for text, lang in zip(batch.column("text"), batch.column("lang").to_pylist()):
            data = text.as_buffer().to_pybytes()
            words.setdefault(lang, Counter()).update(data.lower().split())
            classes[lang] = classes.get(lang, 0) + char_classes(data)
        if sum(map(len, words.values())) > 300_000:
            yield out()
    yield out()


class Reference:
    """Histograms of one language: character classes, its commonest words, and how often another word stands."""

    def __init__(self, classes: dict[str, int], words: list[tuple[bytes, int]], total: int):
        self.classes = np.array([classes.get(c, 0) for c in _CLASSES[:-1]])
        self.place = {w: i for i, (w, _) in enumerate(words)}
        self.words = np.array([n for _, n in words] + [total - sum(n for _, n in words)])

    def distances(self, data: bytes) -> tuple[float, float]:
        found, other = np.zeros(len(self.words)), len(self.place)
        for w in data.lower().split():
            found[self.place.get(w, other)] += 1
        return js_distance(char_classes(data), self.classes), js_distance(found, self.words)


def references(docs: DataFrame, top: int = TOP_WORDS) -> dict[str | None, Reference]:
    """A reference for each value of lang (null is one), counted over all documents; `top` words of each reach the driver."""
    rows = docs.select("lang", F.coalesce("text", F.lit("")).alias("text")).mapInArrow(_counted, "lang string, kind string, item binary, n long")
    counts = rows.groupBy("lang", "kind", "item").agg(F.sum("n").alias("n"))
    counts = common.stored(counts)
    rank = Window.partitionBy("lang").orderBy(F.desc("n"), "item")
    first = counts.filter("kind = 'word'").withColumn("rn", F.row_number().over(rank)).filter(F.col("rn") <= top)
    words: dict = {}
    for r in first.orderBy("rn").select("lang", "item", "n").collect():
        words.setdefault(r.lang, []).append((bytes(r.item), r.n))
    totals = {(r.lang, r.kind): r.n for r in counts.groupBy("lang", "kind").agg(F.sum("n").alias("n")).collect()}
    classes: dict = {}
    for r in counts.filter("kind = 'class'").collect():
        classes.setdefault(r.lang, {})[bytes(r.item).decode()] = r.n
    return {lang: Reference(c, words.get(lang, []), totals.get((lang, "word"), 0)) for lang, c in classes.items()}


_OUT = "doc_id long, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, base_failed boolean, class_distance double, word_distance double, kept boolean"


def judge(docs: DataFrame, refs: dict | None = None, guard: int = GUARD_WORDS, most_class: float = MOST_CLASS, most_word: float = MOST_WORD) -> DataFrame:
    """One row of counts, distances and the verdict per document.

    Columns used: doc_id, text, lang. A document fails the base rules with fewer than 10 words or with over 20 % of
    its words in repeated 5-word windows. Otherwise it is kept unless it has `guard` words or more and is farther
    from its language's reference than either bound. A null text has no words; a null lang is a language of its own;
    repeated rows are judged one by one; an empty table gives an empty result.
    """
    refs = references(docs) if refs is None else refs

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in common.pieces(batches):
            rows = []
            for doc_id, text, lang in zip(batch.column("doc_id").to_pylist(), batch.column("text"), batch.column("lang").to_pylist()):
                data = text.as_buffer().to_pybytes()
                c = base_counts(data)
                failed = c[0] < LEAST_WORDS or 100 * c[4] > MOST_REPEATED * c[0]
                near = refs[lang].distances(data) if lang in refs else (0.0, 0.0)
                rows.append((doc_id, *c, failed, *near, not failed and (c[0] < guard or (near[0] <= most_class and near[1] <= most_word))))
            types = [pa.int64()] * 6 + [pa.bool_(), pa.float64(), pa.float64(), pa.bool_()]
            names = [x.split()[0] for x in _OUT.split(", ")]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(list(zip(*rows)) or [()] * len(types), types)], names=names)

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"), "lang").mapInArrow(run, _OUT)


def op7_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge(common.table(spark, sf_dir, "documents"))
