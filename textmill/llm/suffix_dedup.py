"""Removal of repeated byte strings by distributed prefix doubling over sampled positions."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

#: Starts that go by one place, round by round. Every start goes to a place within SHARE of the threshold behind it that
#: its own bytes choose. Places are ranked by BASE of the threshold's bytes first and by twice as many next; then
#: groups of BLOCKS starts by all bytes that their strings have in common, which grow up to the threshold.
SHARE, BASE, BLOCKS, GRAM = 0.4, 0.3, (16, 1), 8
_PLACES = pa.schema([("rank", pa.int64()), ("next", pa.int32()), ("pair", pa.int64()), ("k1", pa.int64()), ("k2", pa.int32()), ("place", pa.int64()), ("lo", pa.int32()), ("hi", pa.int32())])
_PLACES_SQL = "rank long, next int, pair long, k1 long, k2 int, place long, lo int, hi int"
_RANKS = pa.schema([("rank", pa.int64()), ("pair", pa.int64()), ("k1", pa.int64()), ("k2", pa.int32()), ("place", pa.int64()), ("lo", pa.int32()), ("hi", pa.int32()), ("n", pa.int64())])
_RANKS_SQL = "rank long, pair long, k1 long, k2 int, place long, lo int, hi int, n long"
_name = xxhash.xxh3_64_intdigest


def _gram_hashes(data: bytes) -> np.ndarray:
    if len(data) < GRAM:
        return np.zeros(0, np.uint64)
    return common.mixed(np.ndarray((len(data) - GRAM + 1,), np.dtype(">u8"), data, strides=(1,)).astype(np.uint64))


def _wholes(view, place, lo, hi, length: int) -> list[int]:
    """A name of all bytes of each group's strings; groups of different starts have different names."""
    return [_name(view[p - b : p - a + length], (b << 16) + a + 3) - 2**63 for p, a, b in zip(place.tolist(), lo.tolist(), hi.tolist())]


def _first_ranks(window: int, base: int, length: int):
    """Places with the names of their first `base` bytes and of as many behind; places too near to a text's end for a
    start have lo above hi."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in common.pieces(batches):
            cols: list[list] = [[] for _ in _PLACES]
            for text, k1, k2 in zip(batch.column("text"), batch.column("k1").to_pylist(), batch.column("k2").to_pylist()):
                data = text.as_buffer().to_pybytes()
                place, lo, hi = common.anchors(_gram_hashes(data), window)
                fits = place + base <= len(data)
                place, lo, hi = place[fits], np.maximum(lo[fits], place[fits] - (len(data) - length)), hi[fits]
                view, starts = memoryview(data), lo <= hi
                n = len(place)
                rank = [_name(view[p : p + base], 1) - 2**63 for p in place.tolist()]
                nxt = [_name(view[p + base : p + 2 * base], 2) & 0x7FFFFFFF for p in place.tolist()]
                pair = np.zeros(n, np.int64)
                pair[starts] = _wholes(view, place[starts], lo[starts], hi[starts], length)
                for c, x in zip(cols, (np.array(rank, np.int64), np.array(nxt, np.int32), pair, np.full(n, k1), np.full(n, k2, np.int32), place, np.where(starts, lo, 1).astype(np.int32), np.where(starts, hi, 0).astype(np.int32))):
                    c.append(x)
            if cols[0]:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c), f.type) for c, f in zip(cols, _PLACES)], schema=_PLACES)

    return run


def _next_ranks(size: int, length: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in common.pieces(batches):
            cols: list[list] = [[] for _ in range(8)]
            for text, k1, k2, groups in zip(batch.column("text"), batch.column("k1").to_pylist(), batch.column("k2").to_pylist(), batch.column("groups")):
                data = text.as_buffer().to_pybytes()
                g = groups.values.flatten()
                place, lo, hi, times = (x.to_numpy(zero_copy_only=False).astype(np.int64) for x in g)
                times = np.repeat(times, hi // size - lo // size + 1)
                place, lo, hi = common.blocks(place, lo, hi, size)
                view, common_len = memoryview(data), length - size + 1
                core = [_name(view[p : p + common_len], 1) - 2**63 for p in place.tolist()]
                whole = _wholes(view, place, lo, hi, length)
                for c, x in zip(cols, (np.array(core, np.int64), np.array(whole, np.int64), np.full(len(core), k1), np.full(len(core), k2, np.int32), place, lo, hi, times)):
                    c.append(x)
            if cols[0]:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c), f.type) for c, f in zip(cols, _RANKS)], schema=_RANKS)

    return run


def repeated_spans(docs: DataFrame, length: int = 400) -> DataFrame:
    """(k1, k2, start, end, past) of strings in keyed() documents that start in two places or more: `past`, those of
    `length` bytes, all of them; else those of BASE of it that sampled places have.

    Round by round, Spark sorts (rank[i], rank[i + k]) pairs of places, k the ranked length so far, and reranks: a rank
    that one place holds is unique and the place leaves. Sampled places double their ranked length until it is what
    all strings of a place's starts have in common. Then groups of starts alike to their last byte are past the
    threshold and become spans; one of each kind within a rank of several kinds goes on, with the number it stands
    for, cut into smaller groups that have more bytes in common. Spans of a document may overlap. Ranks are names by
    hash: dense ones would need one global order in every round and move more.
    """
    docs_by_key = docs.select("k1", "k2", "text")
    window = max(int(length * SHARE), 1)
    base = min(int(length * BASE), (length - window + 1) // 2)
    first = common.stored(docs_by_key.mapInArrow(_first_ranks(window, base, length), _PLACES_SQL))

    def held_twice(df: DataFrame) -> DataFrame:
        return common.dealt_join(df, df.groupBy("rank").agg(F.count("*").alias("n")).filter("n > 1").select("rank"), "rank")

    places = common.stored(held_twice(first))
    common.dropped(first)
    doubled = places.filter("lo <= hi").withColumn("rank", F.xxhash64("rank", "next")).drop("next").withColumn("n", F.lit(1).cast("long"))
    ranks = common.stored(held_twice(doubled))
    out = places.select("k1", "k2", F.col("place").alias("start"), (F.col("place") + base).alias("end"), F.lit(False).alias("past"))
    for size in (*(b for b in BLOCKS if b < window), None):
        kinds = ranks.groupBy("rank", "pair").agg(F.sum("n").alias("n"), F.min(F.struct("k1", "k2", "place", "lo", "hi")).alias("at"))
        past = common.dealt_join(ranks, kinds.filter("n > 1").select("rank", "pair"), "rank", "pair")
        out = out.unionByName(past.select("k1", "k2", (F.col("place") - F.col("hi")).alias("start"), (F.col("place") - F.col("lo") + length).alias("end"), F.lit(True).alias("past")))
        if size:
            several = kinds.groupBy("rank").agg(F.count("*").alias("m")).filter("m > 1").select("rank")
            on = common.dealt_join(kinds, several, "rank").select("n", "at.*")
            groups = on.groupBy("k1", "k2").agg(F.collect_list(F.struct("place", "lo", "hi", "n")).alias("groups"))
            ranks = docs_by_key.join(groups, ["k1", "k2"]).select("k1", "k2", "text", "groups").mapInArrow(_next_ranks(size, length), _RANKS_SQL)
    return out


_CUT = pa.schema([("doc_id", pa.int64()), ("n_bytes", pa.int64()), ("n_removed", pa.int64()), ("n_spans", pa.int64()), ("n_shared", pa.int64()), ("kept", pa.binary()), ("spans", pa.list_(pa.list_(pa.int64())))])


def _cut(digest: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in common.pieces(batches):
            rows = []
            for doc_id, text, spans, shared in zip(batch.column("doc_id").to_pylist(), batch.column("text"), batch.column("spans").to_pylist(), batch.column("shared").to_pylist()):
                data = text.as_buffer().to_pybytes()
                runs = common.merged([(s["start"], s["end"]) for s in spans or ()])
                n_shared = sum(b - a for a, b in common.merged(runs + [(s["start"], s["end"]) for s in shared or ()]))
                kept, at = [], 0
                for a, b in runs:
                    kept.append(data[at:a])
                    at = b
                kept = b"".join([*kept, data[at:]]) if runs else data
                rows.append((doc_id, len(data), len(data) - len(kept), len(runs), n_shared, hashlib.sha256(kept).hexdigest() if digest else kept, [list(r) for r in runs]))
            cols = list(zip(*rows)) or [()] * 7
            if digest:
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols[:6], [pa.int64()] * 5 + [pa.string()])], names=["doc_id", "n_bytes", "n_removed", "n_spans", "n_shared", "kept_sha256"])
            else:
                yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(cols, _CUT)], schema=_CUT)

    return run


def remove_repeats(docs: DataFrame, length: int = 400, digest: bool = False) -> DataFrame:
    """Every document without the bytes covered by a string of `length` bytes that also starts elsewhere.

    Columns used: doc_id, text; others are ignored. Returns doc_id, n_bytes, n_removed, n_spans, n_shared and kept
    (binary: a cut may fall inside a character) with spans, or kept_sha256 if `digest`. n_shared counts the bytes under
    removed strings and under the shorter repeats that the sampled places show (BASE of `length`; a repeat of SHARE +
    BASE of it and a few bytes has such a place): what a lower threshold would find. A null text counts as
    empty; a null doc_id and repeated rows are kept as rows of their own, and two rows alike are copies of each
    other; an empty table gives an empty result. Strings are judged on the input.
    """
    if length < 2 * GRAM:
        raise ValueError(f"length must be {2 * GRAM} or more")
    docs = common.keyed(docs)
    found, at = repeated_spans(docs, length), F.struct("start", "end")
    spans = found.groupBy("k1", "k2").agg(F.collect_set(F.when(F.col("past"), at)).alias("spans"), F.collect_set(F.when(~F.col("past"), at)).alias("shared"))
    both = docs.select("k1", "k2", "text").join(spans, ["k1", "k2"], "left").select(common.doc_id_of_key(), "text", "spans", "shared")
    if digest:
        return both.mapInArrow(_cut(True), "doc_id long, n_bytes long, n_removed long, n_spans long, n_shared long, kept_sha256 string")
    return both.mapInArrow(_cut(False), "doc_id long, n_bytes long, n_removed long, n_spans long, n_shared long, kept binary, spans array<array<long>>")


def op3_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = remove_repeats(common.table(spark, sf_dir, "documents"), 400, digest=True)
    return out.select("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "n_shared")
