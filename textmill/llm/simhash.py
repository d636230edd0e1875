"""SimHash near-duplicate groups: fingerprints, BK-trees per shard, connected components."""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations, islice

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StructField, StructType

from . import common

BITS, SEED = 64, 42


def fingerprint(data: bytes, width: int) -> int:
    """SimHash of the `width`-word shingles of lower-cased UTF-8 bytes, repeats included; no word: zero."""
    words = data.lower().split()
    if not words:
        return 0
    text = b" ".join(words)
    if len(words) <= width:
        return xxhash.xxh64_intdigest(text, SEED)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1)
    starts = np.concatenate([[0], ends[:-width]]).tolist()
    h = xxhash.xxh64_intdigest
    hashes = np.fromiter((h(text[a:b], SEED) for a, b in zip(starts, (ends[width - 1 :] - 1).tolist())), np.uint64, len(starts))
    ones = np.zeros(BITS, np.int64)
    for at in range(0, len(hashes), 1 << 15):
        ones += np.unpackbits(hashes[at : at + (1 << 15)].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(ones * 2 > len(hashes), bitorder="little").view(np.uint64)[0])


def _signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def _prints(width: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in common.pieces(batches):
            prints = [_signed(fingerprint(t.as_buffer().to_pybytes(), width)) for t in batch.column("text")]
            yield pa.RecordBatch.from_arrays([*(batch.column(i) for i in range(batch.num_columns - 1)), pa.array(prints, pa.int64())], names=[*batch.schema.names[:-1], "print"])

    return run


class BKTree:
    """Children of a node are keyed by their Hamming distance to it; a search follows edges within the radius only."""

    def __init__(self, first: int):
        self.first, self.children = first, {first: {}}

    def add(self, x: int) -> None:
        at = self.first
        while d := (at ^ x).bit_count():
            nxt = self.children[at].get(d)
            if nxt is None:
                self.children[at][d] = x
                self.children[x] = {}
                return
            at = nxt

    def within(self, x: int, radius: int) -> Iterator[int]:
        stack = [self.first]
        while stack:
            at = stack.pop()
            d = (at ^ x).bit_count()
            if d <= radius:
                yield at
            kids = self.children[at]
            if len(kids) <= 2 * radius + 1:
                stack += [k for e, k in kids.items() if d - radius <= e <= d + radius]
            else:
                stack += [kids[e] for e in range(d - radius, d + radius + 1) if e in kids]


def _links(prints: list[int], radius: int) -> list[tuple[int, int]]:
    """Edges from every member of a linked group to the group's least member, by one BK-tree."""
    parent = {p: p for p in prints}

    def root(x: int) -> int:
        while parent[x] != x:
            parent[x] = parent[parent[x]]
            x = parent[x]
        return x

    tree = BKTree(prints[0])
    for p in prints[1:]:
        for q in tree.within(p, radius):
            a, b = root(p), root(q)
            if a != b:
                parent[max(a, b)] = min(a, b)
        tree.add(p)
    return [(p, r) for p in prints if (r := root(p)) != p]


def _shard(radius: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keys, prints = np.zeros(0, np.int64), np.zeros(0, np.int64)

        def links(k: np.ndarray, p: np.ndarray) -> pa.RecordBatch:
            cut = np.flatnonzero(np.concatenate([[True], k[1:] != k[:-1], [True]]))
            out = [e for a, b in zip(cut[:-1], cut[1:]) if b - a > 1 for e in _links(sorted(set(p[a:b].view(np.uint64).tolist())), radius)]
            pairs = np.array(out, np.uint64).reshape(-1, 2).view(np.int64)
            return pa.RecordBatch.from_arrays([pa.array(pairs[:, 0]), pa.array(pairs[:, 1])], names=["a", "b"])

        for batch in batches:
            keys = np.concatenate([keys, batch.column("key").to_numpy()])
            prints = np.concatenate([prints, batch.column("print").to_numpy()])
            if not len(keys):
                continue
            done = int(np.searchsorted(keys, keys[-1]))  # the last key may go on in the next batch
            yield links(keys[:done], prints[:done])
            keys, prints = keys[done:], prints[done:]
        if len(keys):
            yield links(keys, prints)

    return run


#: Distinct fingerprints from which a shard is split, and how many levels of shards there are: 39, 23 and 14 free bits.
WIDE, LEVELS = 4096, 3


def _narrowed(masks: list[int], radius: int, parts: int) -> list[int]:
    """For each mask of bits that agree, the masks that add all choices of parts - radius parts of its free bits."""
    out = []
    for m in masks:
        free = [i for i in range(BITS) if not m >> i & 1]
        cuts = [len(free) * i // parts for i in range(parts + 1)]
        for chosen in combinations(range(parts), max(parts - radius, 1)):
            out.append(m | sum(1 << i for c in chosen for i in free[cuts[c] : cuts[c + 1]]))
    return out


def links(prints: DataFrame, radius: int = 3, parts: int = 5, wide: int = WIDE) -> DataFrame:
    """Edges (a, b) that connect distinct fingerprints (column print) within `radius` bits, directly or in steps.

    The bits are cut into `parts` parts; two fingerprints within the radius agree in parts - radius parts at least,
    so each is sent to the shards of all such choices, where a BK-tree finds what lies within the radius. A shard
    sends one edge for each member of a group that it links, not all pairs. A shard of more than `wide` fingerprints
    is split in the same way by its free bits; shards of the last level have 14 free bits, so 16,384 at most.
    """
    n = int(prints.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    masks, rows, shards = [0], prints.select("print", F.lit(0).alias("path")), None
    for level in range(LEVELS):
        fan = len(_narrowed([0], radius, parts))
        masks = _narrowed(masks, radius, parts)
        paths = F.sequence(F.col("path") * fan, F.col("path") * fan + (fan - 1))
        agreeing = F.col("print").bitwiseAND(F.get(F.array(*[F.lit(_signed(m)) for m in masks]), F.col("path")))
        rows = rows.select("print", F.explode(paths).alias("path")).withColumn("key", F.xxhash64("path", agreeing))
        split = None
        if level < LEVELS - 1:
            split = common.stored(rows.groupBy("key").agg(F.count("*").alias("n")).filter(F.col("n") > wide).select("key", F.lit(True).alias("split")))
        if split is None or split.isEmpty():
            shards = rows if shards is None else shards.unionByName(rows)
            break
        both = common.dealt_join(rows, split, "key", how="left")
        narrow = both.filter("split is null").drop("split")
        shards = narrow if shards is None else shards.unionByName(narrow)
        rows = both.filter("split").select("print", "path")
    return shards.select("print", "key").repartition(n, "key").sortWithinPartitions("key").mapInArrow(_shard(radius), "a long, b long")


def components(edges: DataFrame) -> DataFrame:
    """(node, root) of every node of an edge table (a, b): root is the least node of its component.

    Alternates large-star and small-star steps; each round is written to the shared folder, and ends when a round
    changes nothing. A node with very many neighbours is split by the join, not gathered.
    """

    def toward(e: DataFrame) -> DataFrame:
        least = e.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("m", "a").alias("m"))
        return common.dealt_join(e, least, "a").select("a", "b", "m")

    e = common.stored(edges.filter("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct())
    seen = None
    while True:
        both = e.union(e.select("b", "a").toDF("a", "b"))
        large = toward(both).filter("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")).distinct()
        small = toward(large)
        e = common.stored(small.filter("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b")).union(small.select("a", "m").toDF("a", "b")).filter("a <> b").distinct())
        now = e.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        if now == seen:
            break
        seen = now
    return e.select(F.col("a").alias("node"), F.col("b").alias("root")).union(e.select(F.col("b").alias("node"), F.col("b").alias("root")).distinct())


def fingerprints(docs: DataFrame, width: int = 3) -> DataFrame:
    """doc_id, print (signed 64-bit SimHash); a null text counts as empty."""
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text")).mapInArrow(_prints(width), "doc_id long, print long")


def near_groups(docs: DataFrame, width: int = 3, radius: int = 3) -> DataFrame:
    """doc_id, fingerprint (16 hex digits) and component_id, the least doc_id reachable by links of `radius` bits.

    Columns used: doc_id, text. Null and empty texts have fingerprint zero and link like any other; a null doc_id
    stays a row and is never a component_id unless its component has no other; repeated rows stay; an empty table
    gives an empty result.
    """
    rows = common.stored(fingerprints(docs, width))
    prints = common.stored(rows.groupBy("print").agg(F.min("doc_id").alias("first")))
    comp = components(links(prints.select("print"), radius))
    rooted = common.stored(prints.join(comp, F.col("print") == F.col("node"), "left").select("print", "first", F.coalesce("root", "print").alias("root")))
    least = rooted.groupBy("root").agg(F.min("first").alias("component_id"))
    label = common.stored(common.dealt_join(rooted, least, "root").select("print", "component_id"))
    hexed = F.lower(F.lpad(F.hex("print"), 16, "0")).alias("fingerprint")
    return common.dealt_join(rows, label, "print").select("doc_id", hexed, "component_id")


def op8_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_groups(common.table(spark, sf_dir, "documents"))


#: Similarity of near-duplicate documents over shingles of so many words; bits within which the trees are searched;
#: minima of which each two make a shard's key; bins of the signature that leaves out the dissimilar, which it may
#: underrate by MARGIN; least shingle hashes that then measure similarity (exact for texts with fewer); how far such an
#: estimate of longer texts may lie from the similarity (over five standard deviations), within which all hashes decide;
#: texts of a shard above which it is cut into blocks.
SIMILARITY, WIDTH, RADIUS, MINIMA, BINS, MARGIN, LEAST, DOUBT, BLOCK = 0.8, 5, 18, 6, 128, 0.16, 1024, 0.07, 256
_FACTORS = np.random.default_rng(5).integers(1, 2**63, MINIMA, dtype=np.uint64) * np.uint64(2) + np.uint64(1)


def _shingles(data: bytes, width: int) -> np.ndarray:
    """Hashes of a text's distinct shingles, in order."""
    w = common.Words(data.lower())
    n = len(w.hashes)
    at = np.arange(max(n - width + 1, 1))
    return np.unique(w.name(at, np.minimum(at + width, n)))


def _sketch(data: bytes, width: int) -> tuple[int, bytes, bytes, list[int]]:
    """SimHash of a text's distinct shingles, a byte of the least hash in each bin (0: none), the least hashes, and the
    keys of its shards."""
    s = _shingles(data, width)
    ones = np.zeros(BITS, np.int64)
    for i in range(0, len(s), 1 << 15):
        ones += np.unpackbits(s[i : i + (1 << 15)].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    bits = int(np.packbits(ones * 2 > len(s), bitorder="little").view(np.int64)[0])
    bins = (s >> np.uint64(57)).astype(np.int64)
    first = np.flatnonzero(np.concatenate([[True], bins[1:] != bins[:-1]]))
    signature = np.zeros(BINS, np.uint8)
    signature[bins[first]] = 1 + (common.mixed(s[first]) % np.uint64(255)).astype(np.uint8)
    least = [(s * f).min() for f in _FACTORS]
    keys = [int(common.mixed((least[i] ^ (least[j] * np.uint64(0x9E3779B97F4A7C15))) + np.uint64(i * MINIMA + j)).view(np.int64)) for i, j in combinations(range(MINIMA), 2)]
    return bits, signature.tobytes(), (s[:LEAST] >> np.uint64(32)).astype("<u4").tobytes(), keys


def _sketches(width: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in common.pieces(batches):
            texts = [t.as_buffer().to_pybytes() for t in batch.column("text")]
            with np.errstate(over="ignore"):
                rows = [_sketch(t, width) for t in texts]
            digest = [xxhash.xxh3_64_intdigest(t) - 2**63 for t in texts]
            cols = list(zip(*rows)) or [()] * 4
            yield pa.RecordBatch.from_arrays(
                [batch.column("k1"), pa.array(digest, pa.int64()), pa.array(cols[0], pa.int64()), pa.array(cols[1], pa.binary()), pa.array(cols[2], pa.binary()), pa.array(cols[3], pa.list_(pa.int64()))],
                names=["k1", "t", "print", "signature", "least", "keys"],
            )

    return run


def _similar(signature: np.ndarray, others: np.ndarray) -> np.ndarray:
    """Estimated Jaccard similarity: bins that agree of those that hold anything."""
    held = ((signature | others) != 0).sum(axis=1)
    return ((signature == others) & (others != 0)).sum(axis=1) / np.maximum(held, 1)


def similarity_of(a: np.ndarray, b: np.ndarray) -> float:
    """Jaccard similarity of two sets of hashes."""
    both = len(np.intersect1d(a, b, assume_unique=True))
    return both / (len(a) + len(b) - both)


def alike(a: np.ndarray, b: np.ndarray, similarity: float) -> bool | None:
    """Whether two texts are similar, by their least hashes (ordered): of the LEAST least of both, those in both. None
    where texts have more hashes and the estimate is too near to the similarity to decide."""
    if len(a) < LEAST and len(b) < LEAST:
        return similarity_of(a, b) >= similarity
    both = np.union1d(a, b)[:LEAST]
    estimate = float((np.isin(both, a, assume_unique=True) & np.isin(both, b, assume_unique=True)).mean())
    return None if abs(estimate - similarity) <= DOUBT else estimate >= similarity


class _Group:
    """Nodes of a shard, joined in groups that go by their least node."""

    def __init__(self, n: int):
        self.of, self.members = np.arange(n), {i: [i] for i in range(n)}

    def join(self, i: int, j: int) -> None:
        a, b = sorted((int(self.of[i]), int(self.of[j])))
        if a != b:
            self.of[self.members[b]] = a
            self.members[a] += self.members.pop(b)


def _alike(prints: list[int], nodes: np.ndarray, roots: list[int], sides: np.ndarray, signatures: np.ndarray, least: list[np.ndarray], radius: int, similarity: float) -> tuple[list[tuple[int, int]], list[int]]:
    """Edges to the least node of each group that similar texts of a shard form, and the nodes of pairs left undecided.

    Texts of one root are in a group from the start. Of a unit of two blocks only texts of different sides are compared;
    side 2 is a block with itself. The texts within the radius come first, from a BK-tree; what is then not in one group with a text is compared with
    it by signature, whatever its SimHash.
    """
    groups, doubt, first = _Group(len(prints)), np.zeros(len(prints), bool), {}
    for i, root in enumerate(roots):
        groups.join(first.setdefault(root, i), i)
    tree, of_print = BKTree(prints[0]), {prints[0]: [0]}

    def compare(i: int, near: np.ndarray) -> None:
        for at in range(0, len(near), 64):
            part = near[at : at + 64]
            part = part[(groups.of[part] != groups.of[i]) & ((sides[part] != sides[i]) | (sides[i] == 2))]
            for j in part[_similar(signatures[i], signatures[part]) >= similarity - MARGIN].tolist():
                if groups.of[i] != groups.of[j]:
                    same = alike(least[i], least[j], similarity)
                    if same:
                        groups.join(i, j)
                    elif same is None:
                        doubt[[i, j]] = True

    for i in range(1, len(prints)):
        near = np.array([j for p in tree.within(prints[i], radius) for j in of_print[p]], np.int64)
        compare(i, near)
        far = groups.of[:i] != groups.of[i]
        far[near] = False
        compare(i, np.flatnonzero(far))
        if prints[i] not in of_print:
            tree.add(prints[i])
        of_print.setdefault(prints[i], []).append(i)
    return [(int(nodes[i]), int(nodes[r])) for i, r in enumerate(groups.of.tolist()) if r != i], [int(nodes[i]) for i in np.flatnonzero(doubt)]


def _by_key(batches: Iterator[pa.RecordBatch], columns: tuple[str, ...]) -> Iterator[list[tuple]]:
    """Rows of each key in turn; rows come ordered by key, the first of the columns."""
    rows: list[tuple] = []
    for batch in batches:
        for row in zip(*(batch.column(c).to_pylist() for c in columns)):
            if rows and rows[0][0] != row[0]:
                yield rows
                rows = []
            rows.append(row)
        del batch
        common.trim()
    if rows:
        yield rows


def _edges(found: Iterator[tuple[int | None, int, int | None]]) -> Iterator[pa.RecordBatch]:
    """Batches of (key, a, b)."""
    while part := list(islice(found, 1 << 13)):
        yield pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in zip(*part)], names=["key", "a", "b"])


def _alike_shards(radius: int, similarity: float):
    """(null, a, b) for each edge; (key, a, null) for each node of an undecided pair of a shard."""

    def found(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int | None, int, int | None]]:
        for part in _by_key(batches, ("key", "t", "root", "side", "print", "signature", "least")):
            if len(part) > 1:
                signatures = np.array([np.frombuffer(r[5], np.uint8) for r in part])
                pairs, open_ = _alike([r[4] & (2**64 - 1) for r in part], np.array([r[1] for r in part]), [r[2] for r in part], np.array([r[3] for r in part]), signatures, [np.frombuffer(r[6], "<u4") for r in part], radius, similarity)
                yield from ((None, a, b) for a, b in pairs)
                yield from ((part[0][0], t, None) for t in open_)

    return lambda batches: _edges(found(batches))


def _all_hashes(width: int):
    """t and all shingle hashes of the texts whose digest is t."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in common.pieces(batches, 64):
            texts = [(t, x.as_buffer().to_pybytes()) for t, x in zip(batch.column("t").to_pylist(), batch.column("text"))]
            with np.errstate(over="ignore"):
                rows = [(t, _shingles(x, width).tobytes()) for t, x in texts if xxhash.xxh3_64_intdigest(x) - 2**63 == t]
            yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int64()), pa.array([r[1] for r in rows], pa.binary())], names=["t", "hashes"])

    return run


def _exact_shards(similarity: float):
    """(key, a, b) for each edge between similar texts of a shard, by all their hashes."""

    def found(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int | None, int, int | None]]:
        for part in _by_key(batches, ("key", "t", "hashes")):
            groups, sets = _Group(len(part)), [np.frombuffer(r[2], np.uint64) for r in part]
            for i in range(len(part)):
                for j in range(i):
                    if groups.of[i] != groups.of[j] and min(len(sets[i]), len(sets[j])) / max(len(sets[i]), len(sets[j])) >= similarity and similarity_of(sets[i], sets[j]) >= similarity:
                        groups.join(i, j)
            yield from ((part[0][0], part[i][1], part[r][1]) for i, r in enumerate(groups.of.tolist()) if r != i)

    return lambda batches: _edges(found(batches))


def _near_signatures(similarity: float):
    """The pairs (t, lead) whose signatures are near."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            a, b = (np.frombuffer(b"".join(batch.column(c).to_pylist()), np.uint8).reshape(-1, BINS) for c in ("signature", "signature_"))
            held, same = ((a | b) != 0).sum(axis=1), ((a == b) & (a != 0)).sum(axis=1)
            yield batch.select(["t", "lead"]).filter(pa.array(same >= (similarity - MARGIN) * np.maximum(held, 1) - 1e-9))

    return run


def _decided(similarity: float):
    """t, lead and whether they are alike; null where the least hashes leave it in doubt."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            least = zip(batch.column("least").to_pylist(), batch.column("least_").to_pylist())
            same = [alike(np.frombuffer(a, "<u4"), np.frombuffer(b, "<u4"), similarity) for a, b in least]
            yield pa.RecordBatch.from_arrays([batch.column("t"), batch.column("lead"), pa.array(same, pa.bool_())], names=["t", "lead", "same"])

    return run


def _exact(similarity: float):
    """The pairs (a, b) that are similar by all their hashes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sets = zip(batch.column("hashes").to_pylist(), batch.column("hashes_").to_pylist())
            same = [similarity_of(np.frombuffer(a, np.uint64), np.frombuffer(b, np.uint64)) >= similarity for a, b in sets]
            yield batch.select(["a", "b"]).filter(pa.array(same, pa.bool_()))

    return run


def _with(pairs: DataFrame, texts: DataFrame, a: str, b: str, column: str) -> DataFrame:
    """pairs with a column of texts for either end."""
    other = texts.select(F.col("t").alias(b), F.col(column).alias(f"{column}_"))
    return pairs.join(texts.select(F.col("t").alias(a), column), a).join(other, b)


def _stars(texts: DataFrame, open_: DataFrame, similarity: float) -> tuple[DataFrame, DataFrame]:
    """(t, lead, same) of pairs compared, and (key, t, root) of shards that are not settled by them.

    Each shard compares its least text with its others, by joins. A text then goes by the least text that it is like, and
    by that one's. A shard is settled when its others go by one text: a group of copies, however large, takes one
    round of joins, and no task holds it.
    """
    leaders = open_.groupBy("key").agg(F.min("t").alias("lead"))
    rays = common.dealt_join(open_, leaders, "key").filter("t <> lead")
    near = _with(rays.select("t", "lead").distinct(), texts, "t", "lead", "signature").mapInArrow(_near_signatures(similarity), "t long, lead long")
    found = common.stored(_with(near, texts, "t", "lead", "least").mapInArrow(_decided(similarity), "t long, lead long, same boolean"))
    like = found.filter("same").groupBy("t").agg(F.min("lead").alias("root"))
    by = like.join(like.select(F.col("t").alias("root"), F.col("root").alias("next")), "root", "left").select("t", F.coalesce("next", "root").alias("root"))
    others = rays.select("key", "t").join(by, "t", "left").withColumn("root", F.coalesce("root", "t"))
    several = others.groupBy("key").agg(F.min("root").alias("x"), F.max("root").alias("y")).filter("x <> y").select("key")
    return found, common.stored(common.dealt_join(others, several, "key"))


def _units(shards: DataFrame, block: int) -> DataFrame:
    """(key, t, root) -> the same with side: a shard of n > `block` texts is cut into blocks, and each two blocks, or one with
    itself, make a unit of work with a key of its own. No task holds a shard, and no pair of texts is left out.

    A text goes to as many units as there are blocks. Blocks of a fixed size would make n^2 / block rows; their number is
    the root of n / block instead, so they grow in size too, and rows grow as n^1.5.
    """
    sizes = common.stored(shards.groupBy("key").agg(F.count("*").alias("n")).filter(F.col("n") > block))
    blocks = sizes.select("key", F.ceil(F.sqrt(F.col("n") / block)).cast("long").alias("blocks"))
    both = common.dealt_join(shards, blocks, "key", how="left").withColumn("blocks", F.coalesce("blocks", F.lit(1).cast("long")))
    own = both.withColumn("own", F.pmod(F.xxhash64("t", F.lit("block")), F.col("blocks"))).withColumn("other", F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1)))
    side = F.when(F.col("own") == F.col("other"), 2).otherwise((F.col("own") > F.col("other")).cast("int"))
    unit = F.when(F.col("blocks") == 1, F.col("key")).otherwise(F.xxhash64("key", F.least("own", "other"), F.greatest("own", "other")))
    return own.select(unit.alias("key"), "t", "root", side.alias("side"))


def keep_one(docs: DataFrame, similarity: float = SIMILARITY, radius: int = RADIUS, width: int = WIDTH) -> DataFrame:
    """The rows of docs, all columns, one of each group of equal or similar texts: the one with the least doc_id.

    Texts are similar if the Jaccard similarity of their sets of `width`-word shingles (lower-cased in
    ASCII) reaches `similarity`; groups are closed under steps. Equal texts are folded first. A text is sent to the
    shards of each two of its six least shingle hashes that another text shares (of two texts at 0.8, all but two in
    a thousand meet). Stars settle the shards whose texts are one group; in the others, large ones in blocks, a BK-tree of SimHashes
    gives the texts within `radius` bits, whose similarity is then measured, and then that of the others whose
    signature is near. Where texts have more than the 1,024 least hashes that are compared and their estimate is in
    doubt, all hashes are made of the texts again and decide. Columns used: doc_id, text. Null and empty texts are
    alike; a null doc_id comes before others; of repeated rows one stays; an empty table stays empty.
    """
    key = F.coalesce(F.col("doc_id").cast("long"), F.lit(-(2**62)))
    text = F.coalesce("text", F.lit(""))
    rows = common.stored(docs.select(key.alias("k1"), text.alias("text")).mapInArrow(_sketches(width), "k1 long, t long, print long, signature binary, least binary, keys array<long>"))
    texts = common.stored(rows.groupBy("t").agg(F.min("k1").alias("k1"), *[F.first(c).alias(c) for c in ("print", "signature", "least", "keys")]))
    common.dropped(rows)
    keys = texts.select("t", F.explode("keys").alias("key"))
    shared = keys.groupBy("key").agg(F.count("*").alias("n")).filter("n > 1").select("key")
    compared, rest = _stars(texts, common.stored(common.dealt_join(keys, shared, "key").distinct()), similarity)
    n = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    sharded = _units(rest, BLOCK).join(texts.select("t", "print", "signature", "least"), "t").select("key", "t", "root", "side", "print", "signature", "least").repartition(n, "key").sortWithinPartitions("key", "t")
    found = common.stored(sharded.mapInArrow(_alike_shards(radius, similarity), "key long, a long, b long"))
    doubt = found.filter("b is null").select("key", F.col("a").alias("t"))
    in_doubt = compared.filter("same is null").select(F.col("t").alias("a"), F.col("lead").alias("b"))
    ends = doubt.select("t").union(in_doubt.select("a")).union(in_doubt.select("b")).distinct()
    wanted = common.stored(texts.join(ends, "t", "left_semi").select("t", F.col("k1").alias("k1_")))
    again = docs.select(key.alias("k1"), text.alias("text")).join(wanted, F.col("k1") == F.col("k1_")).select("t", "text")
    hashes = common.stored(again.mapInArrow(_all_hashes(width), "t long, hashes binary").groupBy("t").agg(F.first("hashes").alias("hashes")))
    exact = doubt.join(hashes, "t").select("key", "t", "hashes").repartition(n, "key").sortWithinPartitions("key", "t")
    decided = exact.mapInArrow(_exact_shards(similarity), "key long, a long, b long").select("a", "b")
    pairs = _with(in_doubt, hashes, "a", "b", "hashes").mapInArrow(_exact(similarity), "a long, b long")
    stars = compared.filter("same").select(F.col("t").alias("a"), F.col("lead").alias("b"))
    comp = components(found.filter("b is not null").select("a", "b").union(decided).union(pairs).union(stars))
    rooted = texts.select("t", "k1").join(comp, F.col("t") == F.col("node"), "left").select("t", "k1", F.coalesce("root", "t").alias("root"))
    kept = rooted.groupBy("root").agg(F.min(F.struct("k1", "t")).alias("m")).select(F.col("m.k1").alias("k1_"), F.col("m.t").alias("t_"))
    packed = docs.select(F.struct(*docs.columns).alias("row_"), key.alias("k1"))  # all columns travel in one, so their names can't clash
    digest = packed.mapInArrow(_with_digest, StructType([*packed.schema.fields, StructField("t", LongType())]))
    one = digest.join(kept, (F.col("k1") == F.col("k1_")) & (F.col("t") == F.col("t_")))
    number = F.row_number().over(Window.partitionBy("k1_", "t_").orderBy(F.lit(1)))
    return one.withColumn("number_", number).filter("number_ = 1").select("row_.*")


def _with_digest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in common.pieces(batches):
        digest = [xxhash.xxh3_64_intdigest(t.as_buffer().to_pybytes() if t.is_valid else b"") - 2**63 for t in batch.column("row_").field("text")]
        yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(digest, pa.int64())], names=["row_", "k1", "t"])
