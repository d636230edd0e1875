"""Byte-pair encoding, plain and bounded by morphemes, and the measures that compare tokenizers."""

from __future__ import annotations

import heapq
import re
from collections import Counter
from collections.abc import Callable, Iterable, Iterator
from itertools import accumulate, repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..catalog import query, table
from ..functions.text import SQL_WORDS, ratio, sql_ratio, words
from ..plans.components import dropped, reliable
from ..plans.spread import spread

#: Affixes of the Latin stand-in, longest match first; a stem keeps three letters at least.
PREFIXES, SUFFIXES, STEM = ("unter", "über", "ver", "zu", "be", "re", "en", "un"), ("ungen", "keit", "heit", "ment", "tion", "ing", "ung", "lich", "able", "ble", "ed", "ly", "es", "en", "er"), 3
_PATTERN = "^(" + "|".join(PREFIXES) + ")?(.{" + str(STEM) + ",}?)(" + "|".join(SUFFIXES) + ")?$"

Segmenter = Callable[[str], list[str]]


def affix_segments(word: str) -> list[str]:
    """Prefix, stem and suffix of a word by affix tables; their concatenation is the word."""
    m = re.match(_PATTERN, word)
    return [x for x in m.groups() if x] if m else [word]


def word_freq(docs: DataFrame) -> DataFrame:
    """(word, cnt): the corpus shrinks to its distinct words, summed in each task before the shuffle."""
    return spread(docs.select("text")).select(F.explode(words("text")).alias("word")).groupBy("word").agg(F.count("*").alias("cnt"))


_SQL_FREQ = f"(SELECT word, count(*) AS cnt FROM (SELECT unnest({SQL_WORDS}) AS word FROM documents) GROUP BY word)"


@query("word_freq", f"SELECT * FROM {_SQL_FREQ}")
def _freq(spark, d):
    return word_freq(table(spark, d, "documents"))


@query("morph_segments", f"SELECT word, list_filter([regexp_extract(word, '{_PATTERN}', 1), regexp_extract(word, '{_PATTERN}', 2), regexp_extract(word, '{_PATTERN}', 3)], lambda x: x <> '') AS pieces FROM {_SQL_FREQ} WHERE regexp_matches(word, '^[a-zß-ÿ]{{6,}}$')")
def morph_segments(spark, d):
    parts = F.filter(F.array(*[F.regexp_extract("word", _PATTERN, i) for i in (1, 2, 3)]), lambda x: x != "")
    return _freq(spark, d).filter(F.col("word").rlike("^[a-zß-ÿ]{6,}$")).select("word", parts.alias("pieces"))


@query("affix_counts", f"SELECT suffix, count(*) AS n FROM (SELECT substr(word, length(word) - k + 1) AS suffix FROM {_SQL_FREQ}, (SELECT unnest([2, 3, 4]) AS k) WHERE length(word) >= k + 3) GROUP BY suffix HAVING count(*) >= 20")
def affix_counts(spark, d):
    """Endings of 2-4 letters by the number of distinct words that carry them: candidates for unsupervised affixes."""
    w = _freq(spark, d).select("word", F.explode(F.array(F.lit(2), F.lit(3), F.lit(4))).alias("k")).filter("length(word) >= k + 3")
    return w.groupBy(F.expr("substr(word, length(word) - k + 1)").alias("suffix")).agg(F.count("*").alias("n")).filter("n >= 20")


_SQL_PAIRS = "SELECT substr(word, i, 1) AS l, substr(word, i + 1, 1) AS r, sum(cnt)::BIGINT AS n FROM (SELECT word, cnt, unnest(range(1, length(word))) AS i FROM {} WHERE length(word) > 1) GROUP BY ALL"


@query("bpe_pair_counts", _SQL_PAIRS.format(_SQL_FREQ))
def pair_counts(spark, d):
    return _pairs_of(_freq(spark, d))


def _pairs_of(pieces: DataFrame) -> DataFrame:
    each = pieces.filter("length(word) > 1").select("word", "cnt", F.explode(F.sequence(F.lit(1), F.length("word") - 1)).alias("i"))
    return each.groupBy(F.expr("substr(word, i, 1)").alias("l"), F.expr("substr(word, i + 1, 1)").alias("r")).agg(F.sum("cnt").alias("n"))


@query("morph_pair_counts", _SQL_PAIRS.format(f"(SELECT unnest(list_filter([regexp_extract(word, '{_PATTERN}', 1), regexp_extract(word, '{_PATTERN}', 2), regexp_extract(word, '{_PATTERN}', 3)], lambda x: x <> '')) AS word, cnt FROM {_SQL_FREQ} WHERE regexp_matches(word, '^[a-zß-ÿ]{{6,}}$'))"))
def morph_pair_counts(spark, d):
    """Pair counts when no pair may cross a morpheme's end: pieces are words of their own, with multiplicity."""
    parts = F.filter(F.array(*[F.regexp_extract("word", _PATTERN, i) for i in (1, 2, 3)]), lambda x: x != "")
    return _pairs_of(_freq(spark, d).filter(F.col("word").rlike("^[a-zß-ÿ]{6,}$")).select("cnt", F.explode(parts).alias("word")))


def bpe_train(pieces: Iterable[tuple[str | list[str], int]], merges: int | None = None, vocab: int | None = None, unit: str = "char", above: int = 0, made: Iterable[str] = ()) -> list[tuple[str, str, int]]:
    """Ordered merges (left, right, count) over (piece, count): most counted first, then the smaller left and right.

    Stops after `merges` merges or when alphabet and merges reach `vocab`; before a merge that isn't counted more than `above`
    times, and, if that is more than none, after one that makes a symbol that is `made` or was made here already. Pieces are the distinct words of a corpus, or
    its morphemes for the bounded variant; either way a merge never crosses a piece. All symbols lie in one array, each
    with the places of its neighbours; a merge takes off the counts of the pairs around it and adds those it makes.
    """
    names: list[str] = []
    number: dict[str, int] = {}
    flat, weight = [], []
    for p, c in pieces:
        symbols = [chr(x) for x in p.encode()] if unit == "byte" else p
        for x in symbols:
            if x not in number:
                number[x] = len(names)
                names.append(x)
        flat += [number[x] for x in symbols]
        flat.append(-1)  # no pair reaches over it
        weight += [c] * (len(symbols) + 1)
    seq, w = np.array([-1, *flat, -1], np.int32), np.array([0, *weight, 0], np.int64)
    after, before = np.arange(1, len(seq) + 1, dtype=np.int32), np.arange(-1, len(seq) - 1, dtype=np.int32)
    limit = merges if merges is not None else max(0, (vocab or 0) - len(names))
    known = set(made)
    total: Counter = Counter()

    def count(at: np.ndarray) -> Counter:
        """Weights of the pairs that begin at the places."""
        at = at[seq[at] >= 0]
        then = seq[after[at]]
        at, then = at[then >= 0], then[then >= 0]
        code, which = np.unique(seq[at].astype(np.int64) << 32 | then, return_inverse=True)
        sums = np.zeros(len(code), np.int64)
        np.add.at(sums, which, w[at])
        return Counter({(k >> 32, k & 0xFFFFFFFF): n for k, n in zip(code.tolist(), sums.tolist())})

    total.update(count(np.arange(len(seq))))
    entry = lambda pair: (-total[pair], names[pair[0]], names[pair[1]], pair)
    heap = [entry(pair) for pair in total]
    heapq.heapify(heap)
    out: list[tuple[str, str, int]] = []
    while heap and len(out) < limit:
        n, left, right, (a, b) = heapq.heappop(heap)
        if total[a, b] != -n or n == 0:
            continue
        if -n <= above:
            break
        out.append((left, right, -n))
        if above and left + right in known:
            break
        known.add(left + right)
        at = np.flatnonzero(seq == a)
        at = at[seq[after[at]] == b]
        if a == b:  # of a run, every second place from its first
            start = np.flatnonzero(np.concatenate([[True], after[at[:-1]] != at[1:]]))
            at = at[(np.arange(len(at)) - np.repeat(start, np.diff(start, append=len(at)))) % 2 == 0]
        gone = count(np.unique(np.concatenate([before[at], at, after[at]])))
        new = number.setdefault(left + right, len(names))
        if new == len(names):
            names.append(left + right)
        second = after[at]
        third = after[second]
        seq[at], seq[second] = new, -2  # -2: no longer there
        after[at], before[third] = third, at
        fresh = count(np.unique(np.concatenate([before[at], at])))
        total.subtract(gone)
        total.update(fresh)
        for pair in gone | fresh:
            if total[pair] > 0:
                heapq.heappush(heap, entry(pair))
    return out


def _joined(q: list[str], pair: tuple[str, str]) -> list[str]:
    """q with every pair, from the left, as one symbol."""
    new, k = [], 0
    while k < len(q):
        two = k + 1 < len(q) and (q[k], q[k + 1]) == pair
        new.append(q[k] + q[k + 1] if two else q[k])
        k += 2 if two else 1
    return new


def safe_prefix(top: list[tuple[str, str, int]], limit: int, whole: bool) -> list[tuple[str, str, int]]:
    """The merges that can be made at once: the longest run of the commonest pairs, none of which has a symbol of another.

    Such merges leave each other's counts alone, and what a merge makes is at most as common as a pair that shares a
    symbol with it, at which the run ends; so one at a time the trainer would have made the same ones in the same
    order. Pairs as common as one that is next must be free of touched symbols too, or what a merge made could come
    before it. `whole`: the list holds all pairs, not only the commonest."""
    out: list[tuple[str, str, int]] = []
    touched: set[str] = set()
    at = 0
    while at < len(top) and len(out) < limit:
        end = at
        while end < len(top) and top[end][2] == top[at][2]:
            end += 1
        ends_within = end == len(top) and not whole  # pairs as common may be missing from the list
        for k in range(at, end):
            if len(out) == limit or (out and (ends_within or any(a in touched or b in touched for a, b, _ in top[k:end]))):
                return out
            out.append(top[k])
            touched |= set(top[k][:2])
        at = end
    return out


#: Characters come before merged symbols; words that a task holds as one array.
_MERGED, _HELD = 0x110000, 200_000


def _after(merged: list[tuple[str, str, int]]):
    """What maps batches of (word, cnt) to arrays of their symbols after the merges, a word's end at -1, and of their words' counts."""
    names: dict[str, int] = {}
    number = lambda x: ord(x) if len(x) == 1 else names.setdefault(x, _MERGED + len(names))
    steps = [(number(a), number(b), number(a + b)) for a, b, _ in merged]

    def symbols(words_: list[str], cnt: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
        seq = np.frombuffer("\n".join([*words_, ""]).encode("utf-32-le"), "<u4").astype(np.int64)
        seq[seq == 10] = -1  # words hold no line ends
        for a, b, new in steps:
            at = np.flatnonzero(seq[:-1] == a)
            at = at[seq[at + 1] == b]
            if a == b and len(at):  # of a run, every second place from its first
                start = np.flatnonzero(np.diff(at, prepend=-2) != 1)
                at = at[(np.arange(len(at)) - np.repeat(start, np.diff(start, append=len(at)))) % 2 == 0]
            if len(at):
                seq[at] = new
                seq = np.delete(seq, at + 1)
        return seq, np.concatenate(cnt)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        held, cnt = [], []
        for b in batches:
            held += b.column("word").to_pylist()
            cnt.append(b.column("cnt").to_numpy())
            if len(held) >= _HELD:
                yield symbols(held, cnt)
                held, cnt = [], []
        if held:
            yield symbols(held, cnt)

    return run, names


def bpe_train_rounds(pieces: DataFrame, merges: int, top: int = 500, most: int | None = None) -> list[tuple[str, str, int]]:
    """bpe_train() for more pieces (word, cnt) than a driver holds.

    In each round Spark counts the pairs of all pieces, and the driver trains on what is left of the pieces when they are cut
    at all but the commonest pairs: far fewer different parts, each with its count. A pair over a cut is at most as common as
    the commonest pair that was cut, so merges above that are the trainer's own. A symbol made in two ways may have a cut
    beside one and none beside the other; a round ends with the merge that makes it. `most`: parts that the driver takes.
    """
    most, out = most or TYPES, []
    while len(out) < merges:
        symbols, names = _after(out)

        def pairs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for seq, cnt in symbols(batches):
                at = np.flatnonzero((seq[:-1] >= 0) & (seq[1:] >= 0))
                code, which = np.unique(seq[at] << 32 | seq[at + 1], return_inverse=True)
                n = np.zeros(len(code), np.int64)
                np.add.at(n, which, cnt[(np.cumsum(seq < 0))[at]])
                yield pa.RecordBatch.from_arrays([pa.array(code), pa.array(n)], names=["pair", "n"])

        ranked = reliable(pieces.select("word", "cnt").mapInArrow(pairs, "pair long, n long").groupBy("pair").agg(F.sum("n").alias("n")))
        first, keep = ranked.orderBy(F.desc("n"), "pair").limit(top + 1).collect(), top
        while len(first) > keep and first[0].n == first[keep].n:  # all are as common
            keep *= 4
            first = ranked.orderBy(F.desc("n"), "pair").limit(keep + 1).collect()
        if not first:
            return out
        above = first[keep].n if len(first) > keep else 0
        while True:
            kept = np.sort(np.array([r.pair for r in first if r.n > above], np.int64))

            def parts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
                for seq, cnt in symbols(batches):
                    code = seq[:-1] << 32 | np.maximum(seq[1:], 0)
                    near = np.searchsorted(kept, code)
                    within = (kept[np.minimum(near, len(kept) - 1)] == code) & (seq[:-1] >= 0) & (seq[1:] >= 0)
                    edge = np.diff(within.astype(np.int8), prepend=0, append=0)
                    lo, hi = np.flatnonzero(edge == 1), np.flatnonzero(edge == -1) + 1
                    weight, data, n = cnt[np.cumsum(seq < 0)[lo]].tolist(), seq.astype("<i4").tobytes(), Counter()
                    for i, j, c in zip((4 * lo).tolist(), (4 * hi).tolist(), weight):
                        n[data[i:j]] += c
                    yield pa.RecordBatch.from_arrays([pa.array(list(n), pa.binary()), pa.array(n.values(), pa.int64())], names=["part", "n"])

            found = reliable(pieces.select("word", "cnt").mapInArrow(parts, "part binary, n long").groupBy("part").agg(F.sum("n").alias("n")))
            counts = sorted({r.n for r in first if r.n > above}, reverse=True)
            if len(counts) == 1 or found.count() <= most:
                break
            above = counts[len(counts) // 2]  # fewer pairs, shorter and fewer parts
            dropped(found)
        name = {v: k for k, v in names.items()}
        cut = [([name[x] if x >= _MERGED else chr(x) for x in np.frombuffer(r.part, "<i4").tolist()], r.n) for r in found.toLocalIterator()]
        out += bpe_train(cut, merges - len(out), above=above, made={a + b for a, b, _ in out}) if above else bpe_train(cut, merges - len(out))
        dropped(ranked, found)
        if not above:
            break
    return out


_NO_RANK = 1 << 60


def bpe_encode(word: str, ranks: dict[tuple[str, str], int], unit: str = "char") -> list[str]:
    q = [chr(b) for b in word.encode()] if unit == "byte" else list(word)
    while len(q) > 1:
        r = list(map(ranks.get, zip(q, q[1:]), repeat(_NO_RANK)))
        best = min(r)
        if best == _NO_RANK:
            break
        k = r.index(best)
        if r.count(best) == 1:
            q[k : k + 2] = [q[k] + q[k + 1]]
        else:
            q = _joined(q, (q[k], q[k + 1]))
    return q


def alignment(tokens: list[str], morphemes: list[str], norm: str = "morphemes") -> float:
    """Order-preserving match of tokens and morphemes: longest common subsequence over the morphemes (default), over
    both lengths (dice), or as an edit distance (distance)."""
    row = [0] * (len(morphemes) + 1)
    for t in tokens if not set(morphemes).isdisjoint(tokens) else ():
        last = 0
        for j, m in enumerate(morphemes, 1):
            last, row[j] = row[j], max(row[j], row[j - 1], last + 1 if t == m else 0)
    if norm == "distance":
        return len(tokens) + len(morphemes) - 2 * row[-1]
    return 2 * row[-1] / max(len(tokens) + len(morphemes), 1) if norm == "dice" else row[-1] / max(len(morphemes), 1)


def boundary_f1(tokens: list[str], morphemes: list[str]) -> float:
    ends = lambda xs: set(accumulate(map(len, xs[:-1])))
    a, b = ends(tokens), ends(morphemes)
    return 1.0 if not a and not b else 2 * len(a & b) / max(len(a) + len(b), 1)


#: Word types that a byte-pair trainer on the driver takes; more are trained in rounds of Spark.
TYPES = 500_000


def trained(freq: DataFrame, merges: int, segment: Segmenter, most: int = TYPES) -> tuple[dict, dict]:
    """Ranks of plain and of morpheme-bounded merges of all words (word, cnt)."""

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            n: Counter = Counter()
            for w, c in zip(b.column("word").to_pylist(), b.column("cnt").to_pylist()):
                for p in segment(w):
                    n[p] += c
            yield pa.RecordBatch.from_arrays([pa.array(list(n), pa.string()), pa.array(n.values(), pa.int64())], names=["word", "cnt"])

    pieces = reliable(freq.select("word", "cnt").mapInArrow(cut, "word string, cnt long").groupBy("word").agg(F.sum("cnt").alias("cnt")))

    def ranks(of: DataFrame) -> dict[tuple[str, str], int]:
        few = of.count() <= most
        merged = bpe_train([(r.word, r.cnt) for r in of.orderBy("word").collect()], merges) if few else bpe_train_rounds(of, merges)
        return {(a, b): i for i, (a, b, _) in enumerate(merged)}

    return ranks(freq.select("word", "cnt")), ranks(pieces)


def measured(freq: DataFrame, ways: dict[str, Callable[[str], list[str]]], segment: Segmenter) -> DataFrame:
    """One row of measures of each tokenizer. Each distinct word is encoded once by each, in one pass; a batch sends one row a
    tokenizer."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            words_, cnt = b.column("word").to_pylist(), b.column("cnt").to_pylist()
            morphemes, rows = [segment(w) for w in words_], []
            for name, encode in ways.items():
                s = [0, 0, 0.0, 0.0]
                for w, m, c in zip(words_, morphemes, cnt):
                    t = encode(w)
                    s[0], s[1], s[2], s[3] = s[0] + c * len(t), s[1] + c, s[2] + c * alignment(t, m), s[3] + c * boundary_f1(t, m)
                rows.append((name, *s))
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), (pa.string(), pa.int64(), pa.int64(), pa.float64(), pa.float64()))], names=["tokenizer", "tokens", "words", "a", "f"])

    m = spread(freq.select("word", "cnt")).mapInArrow(run, "tokenizer string, tokens long, words long, a double, f double")
    s = m.groupBy("tokenizer").agg(*[F.sum(c).alias(c) for c in ("tokens", "words", "a", "f")])
    return s.select("tokenizer", "tokens", ratio(F.col("tokens"), F.col("words")).alias("fertility"), F.round(F.col("a") / F.col("words"), 6).alias("alignment"), F.round(F.col("f") / F.col("words"), 6).alias("boundary_f1"))


@query("tokenizer_comparison")
def tokenizer_comparison(spark, d, merges: int = 300):
    """Characters, bytes, plain BPE and morpheme-bounded BPE on fertility and alignment over all words, which are counted
    once. Up to TYPES word types are trained on the driver, more in rounds of Spark."""
    freq = reliable(_freq(spark, d))
    plain, bounded = trained(freq, merges, affix_segments)
    ways = {
        "char": list, "byte": lambda w: [chr(b) for b in w.encode()], "bpe": lambda w: bpe_encode(w, plain),
        "bounded_bpe": lambda w: [t for m in affix_segments(w) for t in bpe_encode(m, bounded)], "bounded_unsegmented": lambda w: bpe_encode(w, bounded), "whitespace": lambda w: [w],
    }
    return measured(freq, ways, affix_segments)


@query("tokenizer_lengths", f"SELECT doc_id, len(w)::BIGINT AS by_word, length(array_to_string(w, ''))::BIGINT AS by_char, strlen(array_to_string(w, ''))::BIGINT AS by_byte FROM (SELECT doc_id, {SQL_WORDS} AS w FROM documents)")
def tokenizer_lengths(spark, d):
    w = table(spark, d, "documents").select("doc_id", words("text").alias("w"))
    j = F.array_join("w", "")
    return w.select("doc_id", F.size("w").cast("bigint").alias("by_word"), F.length(j).cast("bigint").alias("by_char"), F.octet_length(j).cast("bigint").alias("by_byte"))


@query("bytes_per_char", "SELECT lang, round(sum(strlen(text))::DOUBLE / sum(length(text)), 6) AS bytes_per_char FROM documents GROUP BY lang")
def bytes_per_char(spark, d):
    return table(spark, d, "documents").groupBy("lang").agg(F.round(F.sum(F.octet_length("text")) / F.sum(F.length("text")), 6).alias("bytes_per_char"))


@query("fertility", f"SELECT lang, {sql_ratio('sum(length(array_to_string(w, {e})))'.format(e=chr(39) * 2), 'sum(len(w))')} AS fertility FROM (SELECT lang, {SQL_WORDS} AS w FROM documents) GROUP BY lang")
def fertility(spark, d):
    """Tokens per white-space word of the character tokenizer, by language."""
    w = table(spark, d, "documents").select("lang", words("text").alias("w"))
    return w.groupBy("lang").agg(ratio(F.sum(F.length(F.array_join("w", ""))), F.sum(F.size("w"))).alias("fertility"))


@query("vocab_merge", f"WITH f AS (SELECT CASE lang WHEN 'en' THEN 'a' ELSE 'b' END AS v, word, count(*) AS n FROM (SELECT lang, unnest({SQL_WORDS}) AS word FROM documents) GROUP BY ALL), t AS (SELECT word, n FROM f QUALIFY row_number() OVER (PARTITION BY v ORDER BY n DESC, word) <= CASE v WHEN 'a' THEN 640 ELSE 900 END), u AS (SELECT word, sum(n)::BIGINT AS n FROM t GROUP BY word) SELECT word, n FROM u ORDER BY n DESC, word LIMIT 1024 - 64")
def vocab_merge(spark, d, a: int = 640, b: int = 900, multiple: int = 1024, reserved: int = 64):
    """Two vocabularies joined, pruned by frequency so that entries and reserved ones fill a multiple of 1,024."""
    f = table(spark, d, "documents").select(F.when(F.col("lang") == "en", "a").otherwise("b").alias("v"), F.explode(words("text")).alias("word")).groupBy("v", "word").agg(F.count("*").alias("n"))
    rn = F.row_number().over(Window.partitionBy("v").orderBy(F.desc("n"), "word"))
    top = f.withColumn("rn", rn).filter(F.col("rn") <= F.when(F.col("v") == "a", a).otherwise(b))
    return top.groupBy("word").agg(F.sum("n").alias("n")).orderBy(F.desc("n"), "word").limit(multiple - reserved)


@query("vocab_prune", f"SELECT word, cnt FROM {_SQL_FREQ} ORDER BY cnt DESC, word LIMIT 500")
def vocab_prune(spark, d, keep: int = 500):
    return _freq(spark, d).orderBy(F.desc("cnt"), "word").limit(keep)


@query("unigram_token_ppl", f"WITH f AS {_SQL_FREQ} SELECT round(exp(-sum(cnt * ln(cnt::DOUBLE / (SELECT sum(cnt) FROM f))) / sum(cnt)), 4) AS ppl FROM f")
def unigram_ppl(spark, d):
    f = _freq(spark, d)
    n = f.agg(F.sum("cnt").alias("n"))
    return f.join(F.broadcast(n)).agg(F.round(F.exp(-F.sum(F.col("cnt") * F.log(F.col("cnt") / F.col("n"))) / F.sum("cnt")), 4).alias("ppl"))
