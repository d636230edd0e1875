"""Token ids of documents in shard files compressed by Re-Pair grammars, with random-access decoding."""

from __future__ import annotations

import os
import re
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import common

#: Id behind each document; ids of one grammar; share of the sequence that a round of Re-Pair must save for another one to
#: follow; fewest uses of a replaced pair; bits of the hash that counts pairs.
END, SHARD_IDS, LEAST_GAIN, LEAST_USES, BUCKET_BITS = 0, 1_000_000, 0.01, 6, 19
_BREAK = 198  # the id of a line break; its text never joins another piece
_SPACE = re.compile(r"[^\S \n]")
_SUSPECT = np.zeros(256, bool)
_SUSPECT[[9, 11, 12, 13, 28, 29, 30, 31, 0xC2, 0xE1, 0xE2, 0xE3]] = True  # first bytes of white space but blank and line break
_SLOTS, _MOST = 1 << 21, 1_400_000
_LONG = 4096  # bytes of the longest word that is kept; it has no more ids than bytes, so the table's counts hold them


def _odd(data: bytes, b: np.ndarray, edges: np.ndarray) -> np.ndarray:
    """Which texts of a batch (data, b; none empty) have pieces that may reach over a word's end, or special tokens, or end
    in white space, or a word too long for the table."""
    first, last = edges[:-1], edges[1:] - 1
    part = (b == 32) | (b == 10)
    odd = part[first] | part[last]
    inner = np.ones(len(b), bool)
    inner[last] = False  # what stands behind belongs to the next text
    of = lambda at: np.searchsorted(edges, at, "right") - 1
    odd[of(np.flatnonzero(part[:-1] & part[1:] & inner[:-1]))] = True
    odd[of(np.flatnonzero((b[:-1] == 60) & (b[1:] == 124) & inner[:-1]))] = True
    part[first] = True
    starts = np.flatnonzero(part)
    odd[of(starts[np.diff(starts, append=len(b)) > _LONG])] = True
    for i in np.unique(of(np.flatnonzero(_SUSPECT[b]))).tolist():
        odd[i] |= _SPACE.search(data[edges[i] : edges[i + 1]].decode()) is not None
    return odd


class Encoder:
    """Ids of whole texts by a tokenizers file; equal to its own encoding, with each new word encoded once.

    The file's pattern never joins characters across one blank or one line break between words, so words (with the
    blank before them) are encoded apart, and known ones are looked up by hash, all words of a batch at a time. Texts
    with other white space, special tokens or very long words go to the tokenizer whole. A full table keeps the words
    that were met again since they were learnt or kept.
    """

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.apart = self.tokenizer.encode("\n", add_special_tokens=False).ids == [_BREAK]
        self._clear()

    def _clear(self) -> None:
        self.keys, self.first, self.count, self.met = np.zeros(_SLOTS, np.uint64), np.zeros(_SLOTS, np.int32), np.zeros(_SLOTS, np.int16), np.zeros(_SLOTS, bool)
        self.pool, self.used, self.n = np.zeros(1 << 20, np.uint32), 0, 0

    def _find(self, h: np.ndarray) -> np.ndarray:
        """The slot of each hash, or -1."""
        slot = (h & np.uint64(_SLOTS - 1)).astype(np.int64)
        key = self.keys[slot]
        todo = np.flatnonzero((key != h) & (key != 0))
        while len(todo):
            slot[todo] = (slot[todo] + 1) & (_SLOTS - 1)
            key[todo] = self.keys[slot[todo]]
            todo = todo[(key[todo] != h[todo]) & (key[todo] != 0)]
        slot[key == 0] = -1
        return slot

    def _ids_of(self, words: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """All ids and the number of each word's."""
        ids, counts = [], []
        for e in self.tokenizer.encode_batch_fast([b"\n".join(words[at : at + 200]).decode() for at in range(0, len(words), 200)], add_special_tokens=False):
            x = np.array(e.ids, np.uint32)
            cut = np.concatenate([[-1], np.flatnonzero(x == _BREAK), [len(x)]])
            ids.append(x[x != _BREAK])
            counts.append(np.diff(cut) - 1)
        return np.concatenate(ids), np.concatenate(counts)

    def _enter(self, h: np.ndarray, ids: np.ndarray, counts: np.ndarray) -> None:
        """Enters words that the table doesn't hold, by hash, with their ids."""
        while self.used + len(ids) > len(self.pool):
            self.pool = np.concatenate([self.pool, np.zeros_like(self.pool)])
        self.pool[self.used : self.used + len(ids)] = ids
        first = np.cumsum(counts) - counts + self.used
        self.used, self.n = self.used + len(ids), self.n + len(h)
        slot, todo = (h & np.uint64(_SLOTS - 1)).astype(np.int64), np.arange(len(h))
        while len(todo):
            free = todo[self.keys[slot[todo]] == 0]
            self.keys[slot[free]] = h[free]  # of several for one slot the last stays
            won = free[self.keys[slot[free]] == h[free]]
            self.first[slot[won]], self.count[slot[won]] = first[won], counts[won]
            todo = todo[self.keys[slot[todo]] != h[todo]]
            slot[todo] = (slot[todo] + 1) & (_SLOTS - 1)

    def _renew(self) -> None:
        """Keeps the words that were met again, if they leave half of the table."""
        held = np.flatnonzero(self.met & (self.keys != 0))
        h, first, count, pool = self.keys[held], self.first[held].astype(np.int64), self.count[held].astype(np.int64), self.pool
        self._clear()
        if 2 * len(held) <= _MOST:
            self._enter(h, _runs(pool, first, count), count)

    def _learn(self, data: bytes, h: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> None:
        """Enters the words of a batch that the table doesn't hold."""
        fresh, at = np.unique(h, return_index=True)
        words = [data[x:y] for x, y in zip(starts[at].tolist(), ends[at].tolist())]
        if b"\n" in words:  # the separator itself
            k = words.index(b"\n")
            self._enter(fresh[k : k + 1], np.array([_BREAK], np.uint32), np.array([1]))
            fresh = np.delete(fresh, k)
            del words[k]
        if words:
            self._enter(fresh, *self._ids_of(words))

    def _whole(self, texts: list[bytes], at: list[int], out: list[np.ndarray]) -> list[np.ndarray]:
        for i, e in zip(at, self.tokenizer.encode_batch([texts[i].decode() for i in at], add_special_tokens=False)):
            out[i] = np.array(e.ids, np.uint32)
        return out

    def batch(self, texts: list[bytes]) -> list[np.ndarray]:
        """Ids of each text. Texts whose words together overflow the table go to the tokenizer whole."""
        out = [np.zeros(0, np.uint32)] * len(texts)
        some = [i for i, t in enumerate(texts) if t]
        if not some:
            return out
        data, edges = b"".join(texts[i] for i in some), np.cumsum([0] + [len(texts[i]) for i in some])
        b = np.frombuffer(data, np.uint8)
        odd = _odd(data, b, edges) if self.apart else np.ones(len(some), bool)
        if odd.any():
            whole, some = [i for i, o in zip(some, odd) if o], [i for i, o in zip(some, odd) if not o]
            self._whole(texts, whole, out)
            if not some:
                return out
            data, edges = b"".join(texts[i] for i in some), np.cumsum([0] + [len(texts[i]) for i in some])
            b = np.frombuffer(data, np.uint8)
        new = (b == 32) | (b == 10)
        new[1:] |= b[:-1] == 10
        new[edges[:-1]] = True
        starts = np.flatnonzero(new)
        ends = np.concatenate([starts[1:], [len(b)]])
        h = common.word_hashes(b, starts, ends) | np.uint64(1)
        slot = self._find(h)
        gone = np.flatnonzero(slot < 0)
        self.met[slot[slot >= 0]] = True
        if len(gone):
            if self.n + len(gone) > _MOST:
                self._renew()
                if self.n + len(np.unique(h)) > _MOST:
                    self._clear()
                    if len(np.unique(h)) > _MOST:
                        return self._whole(texts, some, out)
                slot = self._find(h)
                gone = np.flatnonzero(slot < 0)
            self._learn(data, h[gone], starts[gone], ends[gone])
            slot[gone] = self._find(h[gone])
        count = self.count[slot].astype(np.int64)
        ids = _runs(self.pool, self.first[slot].astype(np.int64), count)
        cut = np.concatenate([[0], np.cumsum(count)])[np.searchsorted(starts, edges)]
        for i, x, y in zip(some, cut[:-1].tolist(), cut[1:].tolist()):
            out[i] = ids[x:y]
        return out


def _runs(pool: np.ndarray, first: np.ndarray, count: np.ndarray) -> np.ndarray:
    """pool[first : first + count] of all, one behind the other."""
    stop = np.cumsum(count)
    return pool[np.arange(stop[-1] if len(stop) else 0) + np.repeat(first + count - stop, count)]


_ENCODERS: dict[str, Encoder] = {}


def _encoder(path: str) -> Encoder:
    """One encoder for each worker process, so that its words are learnt once and not by every task. Its library is kept to
    the worker's own thread: the tasks of an executor are as many as its cores."""
    os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
    try:
        from textmill.llm import token_output as own
    except ImportError:
        return Encoder(path)
    if path not in own._ENCODERS:
        own._ENCODERS[path] = Encoder(path)
    return own._ENCODERS[path]


class Grammar:
    """A shard's ids as a sequence of symbols: ids, and nonterminals numbered from `base`, each a pair of symbols."""

    def __init__(self, base: int, rules: np.ndarray, sequence: np.ndarray):
        self.base, self.rules, self.sequence = base, rules.reshape(-1, 2), sequence
        self.lengths = np.ones(len(self.rules), np.int64)
        for a, b in self._levels():
            self.lengths[a:b] = self._sizes(self.rules[a:b]).sum(axis=1)

    def _levels(self) -> Iterator[tuple[int, int]]:
        """Runs of rules that use earlier rules only."""
        high, at = self.rules.max(axis=1).astype(np.int64) - self.base if len(self.rules) else np.zeros(0, np.int64), 0
        while at < len(high):
            end = at + 1
            over = np.flatnonzero(high[at:] >= at)
            end = at + int(over[0]) if len(over) else len(high)
            yield at, max(end, at + 1)
            at = max(end, at + 1)

    def _sizes(self, symbols: np.ndarray) -> np.ndarray:
        """How many ids each symbol stands for."""
        s = symbols.astype(np.int64) - self.base
        return np.where(s >= 0, self.lengths[np.maximum(s, 0)] if len(self.lengths) else 1, 1)

    @classmethod
    def compress(cls, ids: np.ndarray, base: int, gain: float = LEAST_GAIN, least: int = LEAST_USES) -> Grammar:
        """Re-Pair, in rounds that each replace all pairs used `least` times or more, left to right, most used first
        where two overlap; pairs are counted in hash buckets. Ends when no pair is used so often, or when a round
        saved less than `gain` of the sequence."""
        seq, rules, n = ids.astype(np.uint32), [], 0
        while len(seq) > 1:
            code = seq[:-1].astype(np.uint64) << np.uint64(32) | seq[1:]
            bucket = ((code * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - BUCKET_BITS)).astype(np.int64)
            uses = np.bincount(bucket, minlength=1 << BUCKET_BITS).astype(np.int32)[bucket]
            # A pair is taken where it is used more than the pairs on either side, the most used first; of neighbours
            # used alike, such as a run of one id, every second one is.
            start = np.flatnonzero(np.concatenate([[True], uses[1:] != uses[:-1]]))
            level = np.concatenate([[0], uses[start], [0]])
            peak = (level[1:-1] > level[:-2]) & (level[1:-1] > level[2:]) & (level[1:-1] >= least)
            size = np.diff(np.concatenate([start, [len(uses)]]))[peak]
            half = (size + 1) // 2
            at = np.repeat(start[peak], half) + 2 * (np.arange(half.sum()) - np.repeat(np.cumsum(half) - half, half))
            # One pair of each bucket stands for it in this round; another one there waits for the next.
            of, here = bucket[at], code[at]
            stands = np.zeros(1 << BUCKET_BITS, np.uint64)
            stands[of] = here
            same = stands[of] == here
            at, of = at[same], of[same]
            chosen = np.flatnonzero(np.bincount(of, minlength=1 << BUCKET_BITS) >= least)
            if not len(chosen):
                break
            number = np.full(1 << BUCKET_BITS, -1, np.int32)
            number[chosen] = np.arange(len(chosen), dtype=np.int32)
            which = number[of]
            at, which = at[which >= 0], which[which >= 0]
            seq[at] = base + n + which
            keep = np.ones(len(seq), bool)
            keep[at + 1] = False
            seq = seq[keep]
            pairs = stands[chosen]
            rules.append(np.stack([pairs >> np.uint64(32), pairs & np.uint64(0xFFFFFFFF)], axis=1).astype(np.uint32))
            n += len(chosen)
            if len(at) < gain * len(seq):
                break
        return cls(base, np.concatenate(rules) if rules else np.zeros((0, 2), np.uint32), seq)

    def _expanded(self) -> tuple[np.ndarray, np.ndarray]:
        """The ids of all rules, one behind the other, and where each begins."""
        first = np.cumsum(self.lengths) - self.lengths
        flat = np.zeros(int(self.lengths.sum()), np.uint32)
        for a, b in self._levels():
            at = first[a:b]
            for symbols in self.rules[a:b].T:
                size = self._sizes(symbols)
                self._put(flat, symbols, size, at, flat, first)
                at = at + size
        return flat, first

    def _put(self, out: np.ndarray, symbols: np.ndarray, size: np.ndarray, at: np.ndarray, flat: np.ndarray, first: np.ndarray) -> None:
        """Writes the ids of symbols to out, each from its place on."""
        high = symbols >= self.base
        out[at[~high]] = symbols[~high]
        n, to, begin = size[high], at[high], first[symbols[high].astype(np.int64) - self.base]
        ramp = np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n)
        out[np.repeat(to, n) + ramp] = flat[np.repeat(begin, n) + ramp]

    def decode(self, start: int = 0, end: int | None = None) -> np.ndarray:
        """The ids from place start to end, expanding only the symbols that cover them."""
        size = self._sizes(self.sequence)
        offsets = np.concatenate([[0], np.cumsum(size)])
        end = int(offsets[-1]) if end is None else end
        a, b = int(np.searchsorted(offsets, start, "right")) - 1, int(np.searchsorted(offsets, end, "left"))
        out = np.zeros(int(offsets[b] - offsets[a]), np.uint32)
        self._put(out, self.sequence[a:b], size[a:b], offsets[a:b] - offsets[a], *self._expanded())
        return out[start - int(offsets[a]) :][: end - start]


_FILE = pa.schema([("shard", pa.int32()), ("part", pa.int32()), ("doc_ids", pa.list_(pa.int64())), ("n_tokens", pa.list_(pa.int64())), ("first", pa.int64()), ("n_ids", pa.int64()), ("base", pa.int64()), ("rules", pa.binary()), ("rule_lengths", pa.binary()), ("sequence", pa.binary())])
FILE_COLUMNS = "shard int, part int, doc_ids array<long>, n_tokens array<long>, first long, n_ids long, base long, rules binary, rule_lengths binary, sequence binary"


def _packed(x: np.ndarray) -> bytes:
    """Symbols in as few bytes as the largest needs (2, 3 or 4)."""
    x = x.astype("<u4").ravel()
    width = 2 if not len(x) or x.max() < 1 << 16 else 3 if x.max() < 1 << 24 else 4
    return bytes([width]) + x.view(np.uint8).reshape(-1, 4)[:, :width].tobytes()


def _unpacked(data: bytes) -> np.ndarray:
    width = data[0]
    out = np.zeros(((len(data) - 1) // width, 4), np.uint8)
    out[:, :width] = np.frombuffer(data, np.uint8, offset=1).reshape(-1, width)
    return out.view("<u4").ravel()


def _written(path: str, shard_ids: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder, doc_ids, ids, total, part, shard, first = None, [], [], 0, 0, 0, 0

        def out() -> pa.RecordBatch:
            flat = np.concatenate(ids)
            base = max(int(flat.max()) + 1, 1)
            g = Grammar.compress(flat, base)
            row = (shard, part, list(doc_ids), [len(x) for x in ids], first, len(flat), base, _packed(g.rules), _packed(g.lengths), _packed(g.sequence))
            return pa.RecordBatch.from_arrays([pa.array([v], f.type) for v, f in zip(row, _FILE)], schema=_FILE)

        for piece in common.pieces(batches, 256):
            encoder = encoder or _encoder(path)
            texts = encoder.batch([t.as_buffer().to_pybytes() for t in piece.column("text")])
            for doc_id, number, e in zip(piece.column("doc_id").to_pylist(), piece.column("shard").to_pylist(), texts):
                shard = number
                doc_ids.append(doc_id)
                ids.append(np.append(e, np.uint32(END)))
                total += len(e) + 1
                if total >= shard_ids:
                    yield out()
                    doc_ids, ids, total, part, first = [], [], 0, part + 1, first + total
        if ids:
            yield out()
        common.trim()

    return run


def tokenizer_path(name: str = "byte_bpe_50k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def write_tokens(docs: DataFrame, path: str, tokenizer: str | None = None, shard_ids: int = SHARD_IDS) -> str:
    """Writes all documents' ids, each ended by id 0, in ascending doc_id order; returns path.

    Format: Parquet files of rows (shard, part): documents in order with their number of ids, the number of the shard's
    ids before them, and one grammar, whose rules and sequence are little-endian symbols behind a byte that gives their width. Columns used: doc_id, text. A
    null text is empty; a null doc_id comes first; repeated rows are written each; an empty table writes no row.
    Equal doc_ids follow each other in any order of equal texts. Nothing is written by hand to a local disk, so a
    lost task is simply written again.
    """
    n = max(int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")), 1)
    text = F.coalesce("text", F.lit("")).alias("text")
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text).repartitionByRange(n, F.col("doc_id").asc_nulls_first()).sortWithinPartitions(F.col("doc_id").asc_nulls_first(), "text")
    rows.select("doc_id", "text", F.spark_partition_id().alias("shard")).mapInArrow(_written(tokenizer or tokenizer_path(), shard_ids), FILE_COLUMNS).write.parquet(path)
    return path


def grammar_of(row) -> Grammar:
    return Grammar(row["base"], _unpacked(bytes(row["rules"])), _unpacked(bytes(row["sequence"])))


def _read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in common.pieces(batches, 1):
        for row in batch.to_pylist():
            flat = grammar_of(row).decode().astype("<u4")
            ends = np.cumsum(row["n_tokens"])
            data = flat.tobytes()
            crc = [zlib.crc32(data[4 * (e - n) : 4 * e]) for e, n in zip(ends.tolist(), row["n_tokens"])]
            start = (row["offset"] + ends - np.array(row["n_tokens"])).tolist()
            yield pa.RecordBatch.from_arrays([pa.array(row["doc_ids"], pa.int64()), pa.array(start, pa.int64()), pa.array(row["n_tokens"], pa.int64()), pa.array(crc, pa.int64())], names=["doc_id", "start", "n_tokens", "ids_crc32"])


def read_tokens(spark: SparkSession, path: str) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of every document, decoded from the files. The ids before a shard are summed
    from one number a shard; a grammar's own row has the number of those before it in its shard."""
    files = spark.read.schema(FILE_COLUMNS).parquet(path)
    sizes = files.groupBy("shard").agg(F.sum("n_ids").alias("n"))
    before = F.sum("n").over(Window.orderBy("shard").rowsBetween(Window.unboundedPreceding, -1))
    shards = sizes.select("shard", F.coalesce(before, F.lit(0)).alias("before"))
    placed = files.join(F.broadcast(shards), "shard").withColumn("offset", F.col("before") + F.col("first"))
    return placed.select("doc_ids", "n_tokens", "offset", "base", "rules", "sequence").mapInArrow(_read, "doc_id long, start long, n_tokens long, ids_crc32 long")


def token_output(docs: DataFrame, tokenizer: str | None = None) -> DataFrame:
    return read_tokens(docs.sparkSession, write_tokens(docs, common.shared_dir(docs.sparkSession), tokenizer))


def op2_token_output(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_output(common.table(spark, sf_dir, "documents"))
