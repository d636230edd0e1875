"""Exact joins of sets by their Jaccard similarity, without a row for each element of each set."""

from __future__ import annotations

import math
from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .components import connected_components, reliable
from .spread import spread

#: Elements that a task counts at a time; ranges of hashes; bits that a hash is counted by; bits of the largest table of levels.
CHUNK, RANGES, BITS, TABLE_BITS = 4_000_000, 256, 40, 27
#: Sets of a block that are compared at once; sets that hold an element for it to be counted by a matrix product.
BLOCK, DENSE = 1000, 32
#: Similarities are rounded to six digits before they are compared.
ROUNDING = 1e-6

Sets = Callable[[pa.RecordBatch], Iterator[tuple[list, list[np.ndarray]]]]


def needed(n: np.ndarray | int, least: float) -> np.ndarray:
    """Elements of a set of n that a set as similar as `least` has too."""
    return np.ceil((least - ROUNDING) * np.asarray(n) - 1e-9).astype(np.int64)


def _counted(sets: Sets):
    """(range, deltas, counts): hashes of many sets by their first bits, sorted, as planes of the bytes of their differences."""

    def sent(held: list[np.ndarray]) -> pa.RecordBatch:
        v, n = np.unique(np.concatenate(held) >> np.uint64(64 - BITS), return_counts=True)
        ends = np.searchsorted(v, np.arange(RANGES + 1, dtype=np.uint64) << np.uint64(BITS - 8))
        rows = [], [], []
        for k in np.flatnonzero(np.diff(ends)).tolist():
            at = slice(ends[k], ends[k + 1])
            low = v[at].astype(np.uint32)
            gaps = np.diff(low, prepend=np.uint32(0)).astype("<u4")
            for out, x in zip(rows, (k, gaps.view(np.uint8).reshape(-1, 4).T.tobytes(), np.minimum(n[at], 255).astype(np.uint8).tobytes())):
                out.append(x)
        return pa.RecordBatch.from_arrays([pa.array(rows[0], pa.int32()), pa.array(rows[1], pa.binary()), pa.array(rows[2], pa.binary())], names=["range", "gaps", "n"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size = [], 0
        for batch in batches:
            for _, some in sets(batch):
                held += some
                size += sum(map(len, some))
                if size >= CHUNK:
                    yield sent(held)
                    held, size = [], 0
        if size:
            yield sent(held)

    return run


def _repeated(key: tuple, group: pa.Table) -> pa.Table:
    """Of a range, the hashes that two sets or more have, and the logarithm of their number."""
    v = [np.cumsum(np.frombuffer(x, np.uint8).reshape(4, -1).T.copy().view("<u4").ravel(), dtype=np.uint32) for x in group["gaps"].to_pylist()]
    n = np.concatenate([np.frombuffer(x, np.uint8) for x in group["n"].to_pylist()]).astype(np.int64)
    value, which = np.unique(np.concatenate(v), return_inverse=True)
    total = np.bincount(which, weights=n)
    value, level = value[total > 1], np.minimum(np.log2(total[total > 1]).astype(np.uint8), 15)
    return pa.table({"range": pa.array([key[0].as_py()], pa.int32()), "size": pa.array([len(value)], pa.int64()), "value": pa.array([value.astype("<u4").tobytes()], pa.binary()), "level": pa.array([level.tobytes()], pa.binary())})


def levels(df: DataFrame, sets: Sets) -> tuple[int, np.ndarray]:
    """(bits, table): for the first bits of a hash, 0 if surely no two sets have it, else about the logarithm of how many do.

    About three bytes an element are shuffled. The table has 64 MB at most and then says of more hashes that they may be shared:
    what follows gets larger, not wrong.
    """
    counted = df.mapInArrow(_counted(sets), "range int, gaps binary, n binary").groupBy("range").applyInArrow(_repeated, "range int, size long, value binary, level binary")
    counted = reliable(counted)
    total = counted.agg(F.sum("size")).first()[0] or 0
    bits = min(TABLE_BITS, max(16, math.ceil(math.log2(16 * total + 1))))

    def segments(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for k, value, level in zip(*(b.column(c).to_pylist() for c in ("range", "value", "level"))):
                cells = np.zeros(1 << (bits - 8), np.uint8)
                np.maximum.at(cells, np.frombuffer(value, "<u4") >> (40 - bits), np.frombuffer(level, np.uint8))
                yield pa.RecordBatch.from_arrays([pa.array([k], pa.int32()), pa.array([(cells[::2] | cells[1::2] << 4).tobytes()], pa.binary())], names=["range", "cells"])

    out = np.zeros((RANGES, 1 << (bits - 9)), np.uint8)
    for r in counted.mapInArrow(segments, "range int, cells binary").toLocalIterator():
        out[r.range] = np.frombuffer(r.cells, np.uint8)
    return bits, out.ravel()


def live_sets(df: DataFrame, sets: Sets, least: float) -> DataFrame:
    """(id, d, n, p, s) of the sets that can have one as similar as `least`: digest, size, the elements that others may have,
    rarest first, and how many of them, from the first, two such sets share one of at least.

    At least needed() elements must be shared; so of the elements in one order for all sets, the first ones up to the size less
    that number, and one more, have one in common. Elements that nothing else has come first in that order and are left out.
    """
    df = spread(df)
    bits, cells = levels(df, sets)
    table = df.sparkSession.sparkContext.broadcast(cells)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for ids, some in sets(batch):
                sizes = np.array([len(x) for x in some], np.int64)
                flat = np.concatenate([*some, np.zeros(0, np.uint64)])
                at = (flat >> np.uint64(64 - bits)).astype(np.int64)
                level = table.value[at >> 1] >> (4 * (at & 1)).astype(np.uint8) & 15
                ends = np.concatenate([[0], np.cumsum(sizes)])
                shared = np.diff(np.concatenate([[0], np.cumsum(level > 0)])[ends])
                need = needed(sizes, least)
                out = [], [], [], [], []
                for k in np.flatnonzero((shared >= need) & (sizes > 0)).tolist():
                    x, own = flat[ends[k] : ends[k + 1]], level[ends[k] : ends[k + 1]]
                    order = np.argsort(own, kind="stable")[len(x) - shared[k] :]  # x is sorted: by level, then by hash
                    for o, v in zip(out, (ids[k], xxhash.xxh3_128_digest(x.tobytes()), len(x), shared[k] - need[k] + 1, x[order].view(np.int64))):
                        o.append(v)
                yield pa.RecordBatch.from_arrays([pa.array(o, t) for o, t in zip(out, (pa.int64(), pa.binary(), pa.int32(), pa.int32(), pa.list_(pa.int64())))], names=["id", "d", "n", "p", "s"])

    return df.mapInArrow(run, "id long, d binary, n int, p int, s array<long>")


def _common(arrays: list[np.ndarray]) -> np.ndarray:
    """Elements that each two of the sets share."""
    m = len(arrays)
    owner = np.repeat(np.arange(m), [len(x) for x in arrays])
    _, which, df = np.unique(np.concatenate(arrays), return_inverse=True, return_counts=True)
    order = np.argsort(which, kind="stable")
    owner, starts = owner[order], np.cumsum(df) - df
    out = np.zeros((m, m), np.float32)
    for k in range(2, min(DENSE, m + 1)):
        first = starts[df == k]
        for lo in range(0, len(first), step := max(1, (1 << 22) // (k * k))):
            held = owner[first[lo : lo + step, None] + np.arange(k)]
            out += np.bincount((held[:, :, None] * m + held[:, None, :]).ravel(), minlength=m * m).reshape(m, m)
    dense = np.flatnonzero(df >= DENSE)
    for lo in range(0, len(dense), 2048):
        some = dense[lo : lo + 2048]
        x = np.zeros((m, len(some)), np.float32)
        x[owner[np.concatenate([np.arange(starts[t], starts[t] + df[t]) for t in some])], np.repeat(np.arange(len(some)), df[some])] = 1
        out += x @ x.T
    return out


def _compared(least: float):
    def run(key: tuple, group: pa.Table) -> pa.Table:
        ids, n, b = (group[c].to_numpy() for c in ("id", "n", "b"))
        flat = group["s"].combine_chunks()
        ends = np.concatenate([[0], np.cumsum(flat.value_lengths().to_numpy())])
        values = flat.flatten().to_numpy()
        both = _common([values[ends[k] : ends[k + 1]] for k in range(len(ids))])
        i, j = np.nonzero((both > 0) & (both >= (least - ROUNDING) * (n[:, None] + n[None, :] - both) - 1e-3) & (ids[:, None] < ids[None, :]))
        if key[1] != key[2]:
            i, j = i[b[i] != b[j]], j[b[i] != b[j]]
        return pa.table({"src": ids[i], "dst": ids[j], "both": both[i, j].astype(np.int64), "either": n[i] + n[j] - both[i, j].astype(np.int64)})

    return run


def compared(sets: DataFrame, edges: DataFrame, least: float) -> DataFrame:
    """(src, dst, both, either) of the pairs of sets (id, n, s) within a component of the edges that are as similar as `least`:
    the numbers of elements they share and have. A component meets in one task; a large one in pairs of blocks."""
    comp = reliable(connected_components(edges))
    blocks = comp.groupBy("comp").agg(F.ceil(F.count("*") / F.lit(BLOCK)).cast("int").alias("k"))
    at = comp.join(blocks, "comp").select("id", "comp", "k", F.pmod(F.xxhash64("id"), "k").cast("int").alias("b"))
    each = sets.select("id", "n", "s").join(at, "id").withColumn("o", F.explode(F.sequence(F.lit(0), F.col("k") - 1)))
    each = each.select("comp", F.least("b", "o").alias("i"), F.greatest("b", "o").alias("j"), "b", "id", F.col("n").cast("long").alias("n"), "s")
    return each.groupBy("comp", "i", "j").applyInArrow(_compared(least), "src long, dst long, both long, either long")


def similar_sets(df: DataFrame, sets: Sets, least: float) -> tuple[DataFrame, DataFrame]:
    """(pairs, members): compared() pairs of the least ids of equal sets, and (id, first) of the sets that are equal to one of
    a lesser id. `sets` gives the ids and the sorted distinct hashes of rows; empty sets are like nothing."""
    live = reliable(live_sets(df, sets, least).filter("id is not null"))
    members = live.join(live.groupBy("d").agg(F.min("id").alias("first"), F.count("*").alias("m")).filter("m > 1"), "d").filter("id <> first").select("id", "first")
    firsts = reliable(live.groupBy("d").agg(F.min("id").alias("id"), F.first("n").alias("n"), F.first("p").alias("p"), F.first("s").alias("s")))
    rare = firsts.select("id", F.explode(F.slice("s", F.lit(1), F.col("p"))).alias("x"))
    stars = rare.groupBy("x").agg(F.min("id").alias("src"), F.count("*").alias("m")).filter("m > 1")
    edges = rare.join(stars, "x").filter("id <> src").select("src", F.col("id").alias("dst")).distinct()
    return compared(firsts, edges, least), members
