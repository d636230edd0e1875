"""What the operators of this folder share: table access, shared storage and word hashing."""

from __future__ import annotations

import ctypes
import re
import tempfile
import uuid

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: White space between words: \x20 and \x09-\x0D, as the contracts have it.
WORD = r"[^\x20\x09-\x0D]+"
IS_SPACE = np.zeros(256, bool)
IS_SPACE[[32, *range(9, 14)]] = True


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """A new folder path under spark.checkpoint.dir, which the driver and all executors see."""
    base = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        base = spark.sparkContext.getCheckpointDir()
        if not base:
            if not re.match(r"local(\[|$)", spark.sparkContext.master):
                raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors see")
            spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="textmill-"))  # one machine: tests and the bench
            base = spark.sparkContext.getCheckpointDir()
    return f"{base.rstrip('/')}/{uuid.uuid4().hex}"


def stored(df: DataFrame, *partition_by: str) -> DataFrame:
    """The rows of df as a table in the shared folder: lineage ends here and a lost executor costs only a reread."""
    path = shared_dir(df.sparkSession)
    df.write.partitionBy(*partition_by).parquet(path) if partition_by else df.write.parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out.stored_at = path
    return out


def dropped(df: DataFrame) -> None:
    """Removes the files of a stored() table that nothing reads any more."""
    context = df.sparkSession.sparkContext
    path = context._jvm.org.apache.hadoop.fs.Path(df.stored_at)
    path.getFileSystem(context._jsc.hadoopConfiguration()).delete(path, True)


def keyed(docs: DataFrame) -> DataFrame:
    """doc_id, text and the key (k1, k2) of a row; rows alike in doc_id and text share one."""
    text = F.coalesce(F.col("text"), F.lit(""))
    return docs.select(
        F.col("doc_id").cast("long").alias("doc_id"),
        text.alias("text"),
        F.coalesce(F.col("doc_id").cast("long"), F.lit(-(2**62) - 1)).alias("k1"),
        F.hash(F.xxhash64(text), F.col("doc_id").isNull()).alias("k2"),
    )


def dealt_join(left: DataFrame, right: DataFrame, *by: str, how: str = "inner") -> DataFrame:
    """left joined to right on long columns, both sides dealt anew by an expression of their own.

    A right side fresh from an aggregation by the same columns would otherwise be joined where it lies, and then
    Spark can't split the rows of a hot key on the left.
    """
    right = right.select(*[F.bitwise_not(c).alias(f"not_{c}") for c in by], *[c for c in right.columns if c not in by])
    on = [F.bitwise_not(c) == F.col(f"not_{c}") for c in by]
    return left.join(right, on, how).drop(*[f"not_{c}" for c in by])


def doc_id_of_key() -> Column:
    return F.when(F.col("k1") != -(2**62) - 1, F.col("k1")).alias("doc_id")


def n_words(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def offsets(lengths: Column) -> Column:
    """Sum of what stands before each element of an array<long>, folded in chunks so that long arrays stay cheap."""
    none = F.array().cast("array<bigint>")
    start = lambda at: F.struct(at.alias("at"), none.alias("out"))
    chunk = lambda at, xs: F.aggregate(xs, start(at), lambda s, x: F.struct((s["at"] + x).alias("at"), F.concat(s["out"], F.array(s["at"])).alias("out")))
    few = chunk(F.lit(0).cast("long"), lengths)["out"]
    firsts = F.sequence(F.lit(1), F.size(lengths), F.lit(256))

    def many(s: Column, i: Column) -> Column:
        part = chunk(s["at"], F.slice(lengths, i, 256))
        return F.struct(part["at"].alias("at"), F.concat(s["out"], part["out"]).alias("out"))

    return F.when(F.size(lengths) <= 256, few).otherwise(F.aggregate(firsts, start(F.lit(0).cast("long")), many)["out"])


_MIX1, _MIX2 = np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)
_R = 0x9E3779B97F4A7C15 | 5
_BYTE = np.random.default_rng(20240607).integers(1, 2**63, 256, dtype=np.uint64)
_POWERS: list[np.ndarray] = []


def mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * _MIX1
    x = (x ^ (x >> np.uint64(27))) * _MIX2
    return x ^ (x >> np.uint64(31))


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of an odd base and of its inverse modulo 2**64."""
    if not _POWERS or len(_POWERS[0]) < n:
        n = max(n, 1 << 16)
        with np.errstate(over="ignore"):
            up, down = (np.multiply.accumulate(np.concatenate([np.ones(1, np.uint64), np.full(n - 1, b, np.uint64)]), dtype=np.uint64) for b in (_R, pow(_R, -1, 2**64)))
        _POWERS[:] = [up, down]
    return _POWERS[0], _POWERS[1]


def trim() -> None:
    """Gives freed memory of a worker process back to the machine; idle workers stay alive between tasks."""
    import pyarrow as pa

    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (OSError, AttributeError):  # another C library
        return


def pieces(batches, rows: int = 1024, size: int = 1 << 20):
    """Slices of Arrow batches of at most `rows` rows and about `size` bytes of text (one row at least), so that what is
    made of a batch stays small; freed memory goes back after each batch."""
    import pyarrow.compute as pc

    for batch in batches:
        upto = None
        if "text" in batch.schema.names:
            upto = np.cumsum(pc.fill_null(pc.binary_length(batch.column("text")), 0).to_numpy(zero_copy_only=False).astype(np.int64))
        at = 0
        while True:
            end = at + rows
            if upto is not None and at < len(upto):
                end = min(end, max(int(np.searchsorted(upto, (upto[at - 1] if at else 0) + size)), at + 1))
            yield batch.slice(at, end - at)
            at = end
            if at >= batch.num_rows:
                break
        del batch
        trim()


def word_spans(data: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """First byte and end of every word of a text's bytes."""
    edge = np.diff(np.concatenate([[0], (~IS_SPACE[data]).view(np.int8), [0]]))
    return np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)


def word_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """A 64-bit hash of every word, equal for equal bytes: differences of one prefix sum over the text."""
    if not len(starts):
        return np.zeros(0, np.uint64)
    up, down = _powers(len(data) + 1)
    total = np.concatenate([np.zeros(1, np.uint64), np.cumsum(_BYTE[data] * up[: len(data)], dtype=np.uint64)])
    return mixed((total[ends] - total[starts]) * down[starts] + (ends - starts).astype(np.uint64))


class Words:
    """A text's words, and prefix sums that name any run of them."""

    def __init__(self, data: bytes):
        self.data, b = data, np.frombuffer(data, np.uint8)
        self.starts, self.ends = word_spans(b)
        self.hashes = word_hashes(b, self.starts, self.ends)
        up, self.down = _powers(len(self.hashes) + 1)
        self.total = [np.concatenate([np.zeros(1, np.uint64), np.cumsum(h * up[: len(h)], dtype=np.uint64)]) for h in (self.hashes, mixed(self.hashes + np.uint64(77)))]

    def name(self, at: np.ndarray, to: np.ndarray, which: int = 0) -> np.ndarray:
        t = self.total[which]
        return mixed((t[to] - t[at]) * self.down[at] + (to - at).astype(np.uint64))


def sliding_min(x: np.ndarray, w: int) -> np.ndarray:
    """Minimum of each w neighbours, by running minima from both ends of blocks of w."""
    n = len(x)
    if n < w:
        return x[:0]
    m = -(-n // w)
    y = np.full(m * w, np.iinfo(x.dtype).max, x.dtype)
    y[:n] = x
    y = y.reshape(m, w)
    left = np.minimum.accumulate(y, axis=1).ravel()
    right = np.minimum.accumulate(y[:, ::-1], axis=1)[:, ::-1].ravel()
    return np.minimum(right[: n - w + 1], left[w - 1 : n])


_PLACE = np.uint64((1 << 27) - 1)


def anchors(grams: np.ndarray, window: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The starts of all windows of a text, dealt to the places of their smallest gram hash (the leftmost of equal ones).

    Equal windows have their anchor at the same offset, whatever stands around them. Returns for every anchor its
    place and the least and largest distance back to a window start that it serves.
    """
    found: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
    step = 1 << 22
    for at in range(0, max(len(grams) - window + 1, 0), step):
        g = grams[at : at + step + window - 1]
        least = sliding_min((g & ~_PLACE) | np.arange(len(g), dtype=np.uint64), window)
        place = (least & _PLACE).astype(np.int64)
        first = np.flatnonzero(np.concatenate([[True], place[1:] != place[:-1]]))
        last = np.concatenate([first[1:], [len(place)]]) - 1
        a = place[first]
        found.append((a + at, a - last, a - first))
    return tuple(np.concatenate(x) for x in zip(*found)) if found else (np.zeros(0, np.int64),) * 3


def blocks(place: np.ndarray, lo: np.ndarray, hi: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Cuts each range lo..hi of distances back from a place at multiples of size; the place moves back to the cut."""
    j0, j1 = lo // size, hi // size
    times = j1 - j0 + 1
    row = np.repeat(np.arange(len(place)), times)
    j = np.arange(len(row)) - np.repeat(np.cumsum(times) - times, times) + j0[row]
    return place[row] - j * size, np.maximum(lo[row] - j * size, 0), np.minimum(hi[row] - j * size, size - 1)


def merged(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """Spans from-to (end exclusive) joined where they overlap or touch."""
    out: list[list[int]] = []
    for a, b in sorted(spans):
        if out and a <= out[-1][1]:
            out[-1][1] = max(out[-1][1], b)
        else:
            out.append([a, b])
    return [(a, b) for a, b in out]
