"""Benchmark decontamination by spaced seeds: hashes under fixed masks find hits, aligned words around them decide."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

#: Fixed masks over word positions: 1 is hashed, 0 may differ.
MASKS = ("111111", "1101111", "11011011", "110110011", "1011010101", "1100110011", "10101110001")
#: Words that an overlap has at least (an item of fewer words: all of them), share of them that agree, bytes of
#: benchmark text whose seeds are sent to the workers (beyond, hashes are joined), bits of the table that then thins
#: out the documents' hashes (a power of two, 32 MB at most).
LEAST_WORDS, SHARE, SENT_BYTES, TABLE_BITS = 13, 0.8, 2_000_000, 28

_PUNCTUATION = np.zeros(256, bool)
_PUNCTUATION[[*range(33, 48), *range(58, 65), *range(91, 97), *range(123, 127)]] = True


def _words(data: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hash and first byte of every word, without punctuation around it; bare punctuation is no word."""
    starts, ends = common.word_spans(data)
    first = starts.copy()
    todo = np.flatnonzero(_PUNCTUATION[data[starts]])
    for _ in range(16):
        if not len(todo):
            break
        starts[todo] += 1
        todo = todo[starts[todo] < ends[todo]]
        todo = todo[_PUNCTUATION[data[starts[todo]]]]
    solid = np.flatnonzero(~_PUNCTUATION[data]) if len(todo) else None  # long runs of punctuation are passed at once
    if solid is not None:
        starts[todo] = np.minimum(np.append(solid, len(data))[np.searchsorted(solid, starts[todo])], ends[todo])
    todo = np.flatnonzero(starts < ends)
    todo = todo[_PUNCTUATION[data[ends[todo] - 1]]]
    for _ in range(16):
        if not len(todo):
            break
        ends[todo] -= 1  # a word that isn't bare punctuation has an end behind its start
        todo = todo[_PUNCTUATION[data[ends[todo] - 1]]]
    if len(todo):
        solid = np.flatnonzero(~_PUNCTUATION[data]) if solid is None else solid
        ends[todo] = solid[np.searchsorted(solid, ends[todo]) - 1] + 1
    kept = starts < ends
    return common.word_hashes(data, starts[kept], ends[kept]), first[kept]


def _seeds(h: np.ndarray, mask: str) -> np.ndarray:
    """The hash under a mask at every word."""
    n = len(h) - len(mask) + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    s = np.full(n, int(mask, 2) * 2 + 1, np.uint64)
    for i, c in enumerate(mask):
        if c == "1":
            s = (s ^ h[i : i + n]) * np.uint64(0x9E3779B97F4A7C15)
            s ^= s >> np.uint64(29)
    return s


def _most_wrong(n: int, share: float) -> int:
    """Words of n that may differ."""
    return n - int(np.ceil(share * n - 1e-9))


def _item_seeds(w: np.ndarray, least: int, share: float) -> Iterator[tuple[str, np.ndarray, np.ndarray]]:
    """(mask, seeds, places) of an item's words. An item of fewer than `least` words has its parts as seeds, one more than
    words that may differ, so one of them always agrees."""
    if len(w) >= least:
        for mask in MASKS:
            s = _seeds(w, mask)
            yield mask, s, np.arange(len(s))
    elif len(w):
        parts = _most_wrong(len(w), share) + 1
        cuts = [len(w) * i // parts for i in range(parts + 1)]
        for a, b in zip(cuts, cuts[1:]):
            if b > a:
                yield "1" * (b - a), _seeds(w[a:b], "1" * (b - a)), np.array([a])


def _hashed(text: str | None) -> np.ndarray:
    return _words(np.frombuffer((text or "").lower().encode(), np.uint8))[0]


def overlap(w: np.ndarray, h: np.ndarray, start: int, least: int, share: float) -> tuple[int, int, int] | None:
    """(from, to, agreeing words) of the longest run of item words w aligned at start of h that agrees by `share`."""
    a, b = max(0, -start), min(len(w), len(h) - start)
    least = min(least, len(w))
    if b - a < least:
        return None
    same = np.concatenate([[0], np.cumsum(w[a:b] == h[start + a : start + b])])
    # A run i..j agrees enough where same - share * place doesn't fall: the longest is found for every start.
    level = same - share * np.arange(len(same))
    best = None
    suffix = np.maximum.accumulate(level[::-1])[::-1]
    for i in range(len(same) - least):
        if suffix[i + least] >= level[i] - 1e-9:
            j = int(np.flatnonzero(level[i + least :] >= level[i] - 1e-9)[-1]) + i + least
            if best is None or j - i > best[1] - best[0]:
                best = (i, j, int(same[j] - same[i]))
    return best and (best[0] + start + a, best[1] + start + a, best[2])


class Seeds:
    """Benchmark items as word hashes, with all their seeds in hash order and a bit table before them."""

    def __init__(self, items: list[tuple[int, str]], least: int = LEAST_WORDS, share: float = SHARE):
        self.ids, self.least, self.share = [i for i, _ in items], least, share
        self.words = [_hashed(t) for _, t in items]
        self.sizes = np.array([len(w) for w in self.words] or [0])
        found = [(mask, s, np.full(len(s), i, np.int32), place.astype(np.int32)) for i, w in enumerate(self.words) for mask, s, place in _item_seeds(w, least, share)]
        self.masks = sorted({f[0] for f in found})
        keys = np.concatenate([*(f[1] for f in found), np.zeros(0, np.uint64)])
        order = np.argsort(keys, kind="stable")
        self.keys = keys[order]
        self.item, self.place = (np.concatenate([*(f[k] for f in found), np.zeros(0, np.int32)])[order] for k in (2, 3))
        self.bits = max(16, int(len(keys) * 16).bit_length())
        self.table = np.zeros(1 << (self.bits - 3), np.uint8)
        at = self.keys >> np.uint64(64 - self.bits)
        np.bitwise_or.at(self.table, (at >> np.uint64(3)).astype(np.int64), np.uint8(1) << (at & np.uint64(7)).astype(np.uint8))

    def hits(self, h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(item, place of the item's first word in h) of all seeds that agree, each diagonal once."""
        found: list[tuple[np.ndarray, np.ndarray]] = [(np.zeros(0, np.int64),) * 2]
        for mask in self.masks:
            s = _seeds(h, mask)
            at = np.flatnonzero(_in_table(self.table, self.bits, s))
            lo, hi = np.searchsorted(self.keys, s[at], "left"), np.searchsorted(self.keys, s[at], "right")
            times = hi - lo
            row = np.repeat(lo, times) + np.arange(times.sum()) - np.repeat(np.cumsum(times) - times, times)
            found.append((self.item[row].astype(np.int64), np.repeat(at, times) - self.place[row]))
        item, start = (np.concatenate(x) for x in zip(*found))
        both = np.unique(np.stack([item, start]), axis=1) if len(item) else np.zeros((2, 0), np.int64)
        return both[0], both[1]

    def possible(self, h: np.ndarray, item: np.ndarray, start: np.ndarray) -> np.ndarray:
        """Which diagonals of short items, whose words must all lie there, agree enough; all others are possible."""
        out, size = np.ones(len(item), bool), self.sizes[item]
        short = np.flatnonzero(size < self.least)
        out[short] = (start[short] >= 0) & (start[short] + size[short] <= len(h))
        short = short[out[short]]
        for i in np.unique(item[short]):
            of, w = short[item[short] == i], self.words[i]
            same = sum((h[start[of] + k] == w[k]).astype(np.int64) for k in range(len(w)))
            out[of] = len(w) - same <= _most_wrong(len(w), self.share)
        return out


def _in_table(table: np.ndarray, bits: int, s: np.ndarray) -> np.ndarray:
    at = s >> np.uint64(64 - bits)
    return (table[(at >> np.uint64(3)).astype(np.int64)] >> (at & np.uint64(7)).astype(np.uint8)) & np.uint8(1) != 0


_OUT = "doc_id long, item_id long, start long, words long, agreeing long"


def _found(seeds: Seeds):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for piece in common.pieces(batches, 256, 1 << 20):
            rows = []
            texts = [t.lower().encode() for t in piece.column("text").to_pylist()]
            ids = piece.column("doc_id").to_pylist()
            edges = np.cumsum([0] + [len(t) + 1 for t in texts])
            h, first = _words(np.frombuffer(b"\n".join([*texts, b""]), np.uint8))
            cut = np.searchsorted(first, edges)
            item, start = seeds.hits(h)
            real = seeds.possible(h, item, start)
            item, start = item[real], start[real]
            # A diagonal belongs to every document that its item's words reach.
            size = seeds.sizes[item]
            lo = np.searchsorted(cut, np.maximum(start, 0), "right") - 1
            hi = np.searchsorted(cut, np.minimum(start + size, len(h)), "left")
            for i, s, x, y in zip(item.tolist(), start.tolist(), lo.tolist(), hi.tolist()):
                for d in range(x, min(y, len(texts))):
                    c0, c1 = int(cut[d]), int(cut[d + 1])
                    if c1 > c0 and (o := overlap(seeds.words[i], h[c0:c1], s - c0, seeds.least, seeds.share)):
                        rows.append((ids[d], seeds.ids[i], o[0], o[1] - o[0], o[2]))
            types = [pa.int64()] * 5
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(list(zip(*rows)) or [()] * 5, types)], names=["doc_id", "item_id", "start", "words", "agreeing"])

    return run


def _item_table(items: DataFrame, least: int, share: float) -> DataFrame:
    """item (a key), item_id, n (words), words (their hashes), seeds (hash and place) of every item."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in common.pieces(batches, 256):
            rows = []
            for item, item_id, text in zip(*(batch.column(c).to_pylist() for c in ("item", "item_id", "text"))):
                w = _hashed(text)
                found = [x for x in _item_seeds(w, least, share)]
                rows.append((item, item_id, len(w), w.tobytes(), [{"seed": s, "place": p} for _, a, b in found for s, p in zip(a.view(np.int64).tolist(), b.tolist())], sorted({m for m, _, _ in found})))
            seed = pa.list_(pa.struct([("seed", pa.int64()), ("place", pa.int32())]))
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(list(zip(*rows)) or [()] * 6, [pa.int64(), pa.int64(), pa.int32(), pa.binary(), seed, pa.list_(pa.string())])], names=["item", "item_id", "n", "words", "seeds", "masks"])

    rows = items.select(F.xxhash64("item_id", F.col("item_id").isNull(), "text").alias("item"), "item_id", "text")
    return common.stored(rows.mapInArrow(run, "item long, item_id long, n int, words binary, seeds array<struct<seed:long,place:int>>, masks array<string>"))


def _joined(docs: DataFrame, items: DataFrame, least: int, share: float) -> DataFrame:
    """(k1, k2, item_id, start, words, agreeing) for keyed() documents, by a join of test and training hashes.

    Nothing that grows goes to the driver: a bit table of fixed size thins the documents' hashes out before the join,
    hits are gathered by document to cut the words at hand out of its text, and these meet the item's words.
    """
    spark = docs.sparkSession
    table = _item_table(items, least, share)
    masks = [r[0] for r in table.select(F.explode("masks")).distinct().collect()]  # one for each mask that any item has
    seeds = table.select("item", "n", F.explode("seeds").alias("s")).select("item", "n", "s.seed", "s.place")
    bits = min(TABLE_BITS, max(16, int(16 * (seeds.count() + 1)).bit_length()))
    at = F.shiftrightunsigned("seed", 64 - bits)
    held = seeds.groupBy(F.shiftrightunsigned(at, 6).cast("int").alias("at")).agg(F.bit_or(F.expr(f"shiftleft(1L, cast(shiftrightunsigned(seed, {64 - bits}) & 63L as int))")).alias("set")).toArrow()
    words = np.zeros(1 << (bits - 6), np.int64)
    words[held["at"].to_numpy()] = held["set"].to_numpy()
    sent = spark.sparkContext.broadcast(words.view(np.uint8))

    def hashes(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in common.pieces(batches, 256):
            cols: list[list[np.ndarray]] = [[np.zeros(0, np.int64)] for _ in range(4)]
            for k1, k2, text in zip(batch.column("k1").to_pylist(), batch.column("k2").to_pylist(), batch.column("text").to_pylist()):
                h = _hashed(text)
                for mask in masks:
                    s = _seeds(h, mask)
                    place = np.flatnonzero(_in_table(sent.value, bits, s))
                    for c, x in zip(cols, (np.full(len(place), k1), np.full(len(place), k2), s[place].view(np.int64), place)):
                        c.append(x)
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c), t) for c, t in zip(cols, [pa.int64(), pa.int32(), pa.int64(), pa.int64()])], names=["k1", "k2", "seed", "at"])

    hits = docs.mapInArrow(hashes, "k1 long, k2 int, seed long, at long").join(seeds, "seed").select("k1", "k2", "item", "n", (F.col("at") - F.col("place")).alias("start")).distinct()
    gathered = hits.groupBy("k1", "k2").agg(F.collect_list(F.struct("item", "n", "start")).alias("hits"))

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in common.pieces(batches, 64):
            rows = []
            for k1, k2, text, found in zip(*(batch.column(c).to_pylist() for c in ("k1", "k2", "text", "hits"))):
                h = _hashed(text)
                for f in found:
                    a = max(f["start"], 0)
                    rows.append((k1, k2, f["item"], f["start"], a, h[a : max(f["start"] + f["n"], a)].tobytes()))
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(list(zip(*rows)) or [()] * 6, [pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.binary()])], names=["k1", "k2", "item", "start", "at", "part"])

    def decide(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for k1, k2, item_id, start, at, part, w in zip(*(batch.column(c).to_pylist() for c in ("k1", "k2", "item_id", "start", "at", "part", "words"))):
                if o := overlap(np.frombuffer(w, np.uint64), np.frombuffer(part, np.uint64), start - at, least, share):
                    rows.append((k1, k2, item_id, o[0] + at, o[1] - o[0], o[2]))
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(list(zip(*rows)) or [()] * 6, [pa.int64(), pa.int32(), *[pa.int64()] * 4])], names=["k1", "k2", "item_id", "start", "words", "agreeing"])

    parts = docs.select("k1", "k2", "text").join(gathered, ["k1", "k2"]).select("k1", "k2", "text", "hits").mapInArrow(cut, "k1 long, k2 int, item long, start long, at long, part binary")
    aligned = parts.join(table.select("item", "item_id", "words"), "item").select("k1", "k2", "item_id", "start", "at", "part", "words")
    return common.stored(aligned.mapInArrow(decide, "k1 long, k2 int, item_id long, start long, words long, agreeing long").distinct())


def _items(benchmark: DataFrame) -> tuple[DataFrame, list[tuple[int, str]] | None]:
    """The distinct items; a list of them too, if it is small."""
    items = benchmark.select(F.col("item_id").cast("long").alias("item_id"), F.coalesce("text", F.lit("")).alias("text")).distinct()
    total = items.agg(F.sum(F.octet_length("text") + 16)).first()[0] or 0
    return items, [(r.item_id, r.text) for r in items.collect()] if total <= SENT_BYTES else None


def overlaps(docs: DataFrame, benchmark: DataFrame, least: int = LEAST_WORDS, share: float = SHARE) -> DataFrame:
    """doc_id, item_id, start, words, agreeing of every aligned overlap of a document with a benchmark item.

    Columns used: doc_id and text; item_id and text. An overlap has `least` words or more (an item of fewer words:
    all its words), of which `share` or more agree at their places. Words are compared lower-cased and without
    punctuation; an item without words overlaps nothing. Null texts are empty; a null doc_id or item_id stays; a
    repeated row gives its overlaps again. Seeds of a benchmark of up to SENT_BYTES are sent to the workers; those of a
    larger one are joined with the documents'.
    """
    items, few = _items(benchmark)
    if few is not None:
        rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"))
        return rows.mapInArrow(_found(Seeds(few, least, share)), _OUT)
    docs = common.keyed(docs)
    found = _joined(docs, items, least, share)
    return docs.select("k1", "k2").join(found, ["k1", "k2"]).select(common.doc_id_of_key(), "item_id", "start", "words", "agreeing")


def contaminated(docs: DataFrame, benchmark: DataFrame, least: int = LEAST_WORDS, share: float = SHARE) -> DataFrame:
    """One row per contaminated document: doc_id, n_items, item_ids (ordered), most_words, most_agreeing."""
    return overlaps(docs, benchmark, least, share).groupBy("doc_id").agg(
        F.count_distinct("item_id").alias("n_items"), F.array_sort(F.collect_set("item_id")).alias("item_ids"), F.max("words").alias("most_words"), F.max("agreeing").alias("most_agreeing")
    )


def keep_clean(docs: DataFrame, benchmark: DataFrame, least: int = LEAST_WORDS, share: float = SHARE) -> DataFrame:
    """The rows of docs, all columns, without an overlap. Repeated rows go or stay alike; null texts and an empty
    benchmark leave all rows; columns of any name are carried along."""
    items, few = _items(benchmark)
    if few is None:
        bad = _joined(common.keyed(docs), items, least, share).select(F.col("k1").alias("k1_"), F.col("k2").alias("k2_")).distinct()
        text = F.coalesce("text", F.lit(""))
        k1, k2 = F.coalesce(F.col("doc_id").cast("long"), F.lit(-(2**62) - 1)), F.hash(F.xxhash64(text), F.col("doc_id").isNull())
        rows = docs.select(F.struct(*docs.columns).alias("row_"), k1.alias("k1"), k2.alias("k2"))  # names can't clash
        return rows.join(bad, (F.col("k1") == F.col("k1_")) & (F.col("k2") == F.col("k2_")), "left_anti").select("row_.*")
    find = _found(Seeds(few, least, share))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in common.pieces(batches):
            text = batch.column("text").fill_null("")
            place = pa.array(range(batch.num_rows), pa.int64())
            bad = {p for b in find(iter([pa.RecordBatch.from_arrays([place, text], names=["doc_id", "text"])])) for p in b.column("doc_id").to_pylist()}
            yield batch.filter(pa.array([i not in bad for i in range(batch.num_rows)], pa.bool_()))

    return docs.mapInArrow(run, docs.schema)


def op5_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return contaminated(common.table(spark, sf_dir, "documents"), common.table(spark, sf_dir, "benchmark"))
