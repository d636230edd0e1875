"""Removal of repeated word passages by compressed FM-indexes, one per shard of passages that can match."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common
from .fm_index import FMIndex

#: Words in a gram whose hash picks a window's anchor; window starts that share one key; contexts of a key that one
#: shard takes (a key with more is split by single windows); words of one index.
GRAM, GROUP, CONTEXTS, SHARD_WORDS = 4, 20, 64, 1_500_000
_KEYS = pa.schema([("core", pa.int64()), ("region", pa.int64()), ("k1", pa.int64()), ("k2", pa.int32()), ("start", pa.int64()), ("words", pa.int32())])
_KEYS_SQL = "core long, region long, k1 long, k2 int, start long, words int"


def _keys(w: common.Words, place, lo, hi, size: int, length: int):
    place, lo, hi = common.blocks(place, lo, hi, size)
    core = w.name(place, place + length - size + 1)
    region = common.mixed(w.name(place - hi, place - lo + length, 1) + hi.astype(np.uint64))
    return core.view(np.int64), region.view(np.int64), place - hi, (hi - lo + length).astype(np.int32)


def _emit(parts: list, schema=_KEYS) -> Iterator[pa.RecordBatch]:
    if parts:
        yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c), f.type) for c, f in zip(zip(*parts), schema)], schema=schema)


def _first_keys(length: int, group: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in common.pieces(batches):
            parts, n = [], 0
            for text, k1, k2 in zip(batch.column("text"), batch.column("k1").to_pylist(), batch.column("k2").to_pylist()):
                w = common.Words(text.as_buffer().to_pybytes())
                if len(w.hashes) < length:
                    continue
                at = np.arange(len(w.hashes) - GRAM + 1)
                core, region, start, words = _keys(w, *common.anchors(w.name(at, at + GRAM), length - GRAM + 1), group, length)
                parts.append((core, region, np.full(len(core), k1), np.full(len(core), k2, np.int32), start, words))
                n += len(core)
                if n > 200_000:
                    yield from _emit(parts)
                    parts, n = [], 0
            yield from _emit(parts)

    return run


_WINDOWS_SQL = "core long, region long, n long, offset int, w0 long, w1 long, k1 long, k2 int, start long, words int"
_WINDOWS = pa.schema([("core", pa.int64()), ("region", pa.int64()), ("n", pa.int64()), ("offset", pa.int32()), ("w0", pa.int64()), ("w1", pa.int64()), ("k1", pa.int64()), ("k2", pa.int32()), ("start", pa.int64()), ("words", pa.int32())])


def _window_keys(length: int):
    """Each single window of the passages of a text, with its own key."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in common.pieces(batches):
            parts = []
            for text, k1, k2, groups in zip(batch.column("text"), batch.column("k1").to_pylist(), batch.column("k2").to_pylist(), batch.column("groups")):
                w = common.Words(text.as_buffer().to_pybytes())
                core, region, n, start, words = (x.to_numpy(zero_copy_only=False).astype(np.int64) for x in groups.values.flatten())
                times = words - length + 1
                row = np.repeat(np.arange(len(start)), times)
                offset = np.arange(len(row)) - np.repeat(np.cumsum(times) - times, times)
                at = start[row] + offset
                parts.append((core[row], region[row], n[row], offset, w.name(at, at + length).view(np.int64), w.name(at, at + length, 1).view(np.int64), np.full(len(at), k1), np.full(len(at), k2, np.int32), at, np.full(len(at), length, np.int32)))
            yield from _emit(parts, _WINDOWS)

    return run


def _texts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The words of each passage, taken from the text of the document that stands for its copies."""
    for batch in common.pieces(batches):
        rows = []
        for text, groups in zip(batch.column("text"), batch.column("groups").to_pylist()):
            words = text.as_buffer().to_pybytes().split()
            rows += [(g["core"], g["region"], g["n"], b" ".join(words[g["start"] : g["start"] + g["words"]])) for g in groups]
        cols = list(zip(*rows)) or [()] * 4
        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, [pa.int64(), pa.int64(), pa.int64(), pa.binary()])], names=["core", "region", "n", "passage"])


_FOUND = pa.schema([("core", pa.int64()), ("region", pa.int64()), ("ranges", pa.list_(pa.list_(pa.int32())))])


def _search(rows: list[tuple[int, int, int, bytes]], length: int) -> pa.RecordBatch:
    """Indexes the passages and streams each through the index: ranges of words whose matching statistics reach length."""
    data = np.frombuffer(b"\n".join([r[3] for r in rows]), np.uint8)
    starts, ends = common.word_spans(data)
    symbols = np.unique(common.word_hashes(data, starts, ends), return_inverse=True)[1].astype(np.int64) + 1
    sizes = np.diff(np.searchsorted(starts, np.cumsum([0] + [len(r[3]) + 1 for r in rows])))
    index = FMIndex(symbols, sizes, np.array([r[2] for r in rows], np.int64), int(symbols.max()) + 1, int(sizes.max()))
    whole = index.match_lengths(index.starts + sizes, sizes)
    ranges = [[[0, s]] if m == s else ([[s - m, s]] if m >= length else []) for s, m in zip(sizes.tolist(), whole.tolist())]
    part = np.flatnonzero(whole < sizes)
    times = sizes[part] - length
    owner = np.repeat(part, times)
    end = sizes[owner] - 1 - (np.arange(len(owner)) - np.repeat(np.cumsum(times) - times, times))
    for at in range(0, len(owner), 1 << 18):
        o, e = owner[at : at + (1 << 18)], end[at : at + (1 << 18)]
        m = index.match_lengths(index.starts[o] + e, e)
        hit = np.flatnonzero(m >= length)
        for k, x, y in zip(o[hit].tolist(), (e - m)[hit].tolist(), e[hit].tolist()):
            ranges[k].append([x, y])
    hit = [i for i, r in enumerate(ranges) if r]
    found = [ranges[i] if len(ranges[i]) == 1 else [list(x) for x in common.merged(ranges[i])] for i in hit]
    return pa.RecordBatch.from_arrays([pa.array([rows[i][0] for i in hit], pa.int64()), pa.array([rows[i][1] for i in hit], pa.int64()), pa.array(found, _FOUND.field(2).type)], schema=_FOUND)


def _shards(length: int):
    """A task's passages come ordered by key; a shard ends with a key, so all that can match stand in one index."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows, words, last = [], 0, None
        for batch in batches:
            for row in zip(*(batch.column(c).to_pylist() for c in ("core", "region", "n", "passage"))):
                if words > SHARD_WORDS and row[0] != last:
                    yield _search(rows, length)
                    rows, words = [], 0
                rows.append(row)
                words += len(row[3]) // 6
                last = row[0]
        if rows:
            yield _search(rows, length)

    return run


def repeated_ranges(docs: DataFrame, length: int = 35, contexts: int = CONTEXTS) -> DataFrame:
    """(k1, k2, start, ranges) of the word passages that stand in two places or more, in keyed() documents.

    Every window of `length` words belongs to an anchor that its own words pick, and equal windows share a key made
    of words around it. Keys seen once are left out; equal passages of a key are counted and sent once. The passages
    of a key meet in one shard, whose FM-index decides. The passages of a key with more than `contexts` different
    ones are dealt by single windows instead, so a text common to very many documents doesn't meet in one task.
    """
    group = min(GROUP, max(length // 2, 1))
    by_doc = docs.select("k1", "k2", "text")
    first = common.stored(by_doc.mapInArrow(_first_keys(length, group), _KEYS_SQL))
    twice = first.groupBy("core").agg(F.count("*").alias("n")).filter("n > 1").select("core")
    places = common.stored(common.dealt_join(first, twice, "core"))
    kinds = places.groupBy("core", "region").agg(F.count("*").alias("n"), F.min(F.struct("k1", "k2", "start", "words")).alias("at"))
    kinds = common.stored(kinds.select("core", "region", "n", "at.*"))
    wide = kinds.groupBy("core").agg(F.count("*").alias("m")).filter(F.col("m") > contexts).select("core")
    narrow = common.dealt_join(kinds, wide, "core", how="left_anti")
    split = common.dealt_join(kinds, wide, "core", how="left_semi").groupBy("k1", "k2").agg(F.collect_list(F.struct("core", "region", "n", "start", "words")).alias("groups"))
    windows = by_doc.join(split, ["k1", "k2"]).select("k1", "k2", "text", "groups").mapInArrow(_window_keys(length), _WINDOWS_SQL)
    single = windows.groupBy("w0", "w1").agg(F.sum("n").alias("n"), F.min(F.struct("k1", "k2", "start", "words")).alias("at")).filter("n > 1")
    sent = narrow.unionByName(single.select(F.col("w0").alias("core"), F.col("w1").alias("region"), "n", "at.*"))
    of_doc = sent.groupBy("k1", "k2").agg(F.collect_list(F.struct("core", "region", "n", "start", "words")).alias("groups"))
    texts = by_doc.join(of_doc, ["k1", "k2"]).select("text", "groups").mapInArrow(_texts, "core long, region long, n long, passage binary")
    n = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    found = texts.repartition(n, "core").sortWithinPartitions("core").mapInArrow(_shards(length), "core long, region long, ranges array<array<int>>")
    # Both joins take the same columns of found in the same dealing, so the indexes are built and searched once.
    of_window = common.dealt_join(windows.select("core", "region", "offset", "w0", "w1"), found.select(F.col("core").alias("w0"), F.col("region").alias("w1"), "ranges"), "w0", "w1")
    here = F.transform(F.element_at("ranges", 1), lambda x: x + F.col("offset"))
    of_window = of_window.groupBy("core", "region").agg(F.collect_list(here).alias("ranges"))
    return common.dealt_join(places, found, "core", "region").select("k1", "k2", "start", "ranges").unionByName(common.dealt_join(places, of_window, "core", "region").select("k1", "k2", "start", "ranges"))


def _cut(digest: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in common.pieces(batches):
            rows = []
            for doc_id, text, found in zip(batch.column("doc_id").to_pylist(), batch.column("text"), batch.column("found").to_pylist()):
                words = text.as_buffer().to_pybytes().split()
                runs = common.merged([(f["start"] + a, f["start"] + b) for f in found or () for a, b in f["ranges"]])
                kept, at = [], 0
                for a, b in runs:
                    kept += words[at:a]
                    at = b
                kept += words[at:]
                out = b" ".join(kept)
                rows.append((doc_id, len(words), len(words) - len(kept), [list(r) for r in runs], hashlib.sha256(out).hexdigest() if digest else out.decode()))
            cols = list(zip(*rows)) or [()] * 5
            types = [pa.int64(), pa.int64(), pa.int64(), pa.list_(pa.list_(pa.int64())), pa.string()]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, types)], names=["doc_id", "n_words", "n_removed", "ranges", "kept_sha256" if digest else "kept"])

    return run


def remove_passages(docs: DataFrame, length: int = 35, digest: bool = False, contexts: int = CONTEXTS) -> DataFrame:
    """Every document without the words covered by a window of `length` words that also starts elsewhere.

    Columns used: doc_id, text; others are ignored. Returns doc_id, n_words, n_removed, ranges (removed words, end
    exclusive) and kept (kept words joined by one blank), or kept_sha256 if `digest`. A null text has no words; a null
    doc_id and repeated rows stay rows of their own, and two rows alike are copies of each other; an empty table gives
    an empty result. Windows are judged on the input.
    """
    if length < GRAM:
        raise ValueError(f"length must be {GRAM} or more")
    docs = common.keyed(docs)
    found = repeated_ranges(docs, length, contexts).groupBy("k1", "k2").agg(F.collect_list(F.struct("start", "ranges")).alias("found"))
    both = docs.select("k1", "k2", "text").join(found, ["k1", "k2"], "left").select(common.doc_id_of_key(), "text", "found")
    return both.mapInArrow(_cut(digest), f"doc_id long, n_words long, n_removed long, ranges array<array<long>>, {'kept_sha256' if digest else 'kept'} string")


def op10_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return remove_passages(common.table(spark, sf_dir, "documents"), 35, digest=True).select("doc_id", "n_words", "n_removed", "kept_sha256")
