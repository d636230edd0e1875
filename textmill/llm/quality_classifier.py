"""Quality scores: random Fourier features of document statistics, ridge by summed normal equations, isotonic calibration."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common
from .quality_rules import _IS_SYMBOL, _TABLE, _CLASSES, repeated_words

#: Random features; ridge penalty; kernel width in standard deviations of a statistic; most labelled rows of a fit;
#: score from which a document is predicted good.
FEATURES, PENALTY, WIDTH, MOST_LABELLED, CUTOFF, SEED = 256, 1e-3, 4.0, 40_000, 0.3, 17


def statistics(data: bytes) -> list[float]:
    """Statistics of one text, none of which depends on its id, language or source."""
    b, w = np.frombuffer(data, np.uint8), common.Words(data)
    n, m = max(len(b), 1), max(len(w.hashes), 1)
    classes = np.bincount(_TABLE[b], minlength=len(_CLASSES))[:-1] / n
    lengths = (w.ends - w.starts) if len(w.hashes) else np.zeros(1)
    counts = np.unique(w.hashes, return_counts=True)[1] if len(w.hashes) else np.ones(1)
    p = counts / counts.sum()
    lines = [x for x in data.split(b"\n") if x.strip()] or [b""]
    last = _TABLE[b[w.ends - 1]] if len(w.hashes) else np.zeros(1, np.int64)
    return [
        *classes.tolist(),
        np.log1p(len(w.hashes)), lengths.mean(), lengths.std(), len(counts) / m, float(-(p * np.log2(p)).sum()) / np.log2(m + 1), float(p.max()),
        len(lines) / m * 10, 1 - len(set(lines)) / len(lines), repeated_words(w) / m, float(_IS_SYMBOL[b].sum()) / m,
        float(np.isin(last, [_CLASSES.index("symbol"), _CLASSES.index("mark")]).mean()), data.count(b"|") / m, float((lengths == 1).mean()),
        float((_TABLE[b[w.starts]] == _CLASSES.index("upper")).mean()) if len(w.hashes) else 0.0, sum(x.rstrip()[-1:] in b".!?" for x in lines) / len(lines),
    ]


_N = len(statistics(b""))


@dataclass
class Model:
    """Everything a worker needs to score a batch: a few hundred KB, whatever the corpus."""

    mean: np.ndarray
    std: np.ndarray
    waves: np.ndarray
    phase: np.ndarray
    weights: np.ndarray
    x: np.ndarray
    y: np.ndarray

    def features(self, stats: np.ndarray) -> np.ndarray:
        z = np.clip((stats - self.mean) / self.std, -8, 8)
        return np.hstack([np.sqrt(2 / len(self.phase)) * np.cos(z @ self.waves + self.phase), z, np.ones((len(z), 1))])

    def raw(self, stats: np.ndarray) -> np.ndarray:
        return self.features(stats) @ self.weights

    def scores(self, stats: np.ndarray) -> np.ndarray:
        return np.interp(self.raw(stats), self.x, self.y)


def isotonic(x: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Knots of the nondecreasing step fit of y on x (pool adjacent violators), joined at the middles of its blocks."""
    order = np.argsort(x, kind="stable")
    stack: list[list[float]] = []
    for a, b in zip(x[order], y[order]):
        stack.append([a, b, 1.0])
        while len(stack) > 1 and stack[-2][1] / stack[-2][2] >= stack[-1][1] / stack[-1][2]:
            s = stack.pop()
            stack[-1] = [stack[-1][0] + s[0], stack[-1][1] + s[1], stack[-1][2] + s[2]]
    knots = np.array([[sx / n, sy / n] for sx, sy, n in stack])
    return knots[:, 0], knots[:, 1]


def _stats_of(batch: pa.RecordBatch) -> np.ndarray:
    return np.array([statistics(t.as_buffer().to_pybytes() if t.is_valid else b"") for t in batch.column("text")], float).reshape(-1, _N)


def _with_stats(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in common.pieces(batches):
        stats = _stats_of(batch)
        yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.FixedSizeListArray.from_arrays(pa.array(stats.ravel()), _N).cast(pa.list_(pa.float64()))], names=["doc_id", "stats"])


def statistics_of(docs: DataFrame) -> DataFrame:
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(_with_stats, "doc_id long, stats array<double>")


def fold(doc_id: Column) -> Column:
    """The remainder 0-4 that deals a document to a fold; 0 is held out."""
    return F.pmod(F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")), F.lit(5)).cast("int")


def chosen(labels: DataFrame, most: int = MOST_LABELLED) -> DataFrame:
    """(id_, quality) of labelled rows outside fold 0, about `most` at most, chosen by a hash of doc_id; stored."""
    good = labels.filter("quality is not null").select(F.col("doc_id").cast("long").alias("id_"), F.col("quality").cast("double").alias("quality"))
    good = common.stored(good.filter(fold(F.col("id_")) != 0))
    n = good.count()
    return good if n <= most else common.stored(good.filter(F.pmod(F.xxhash64("id_"), F.lit(1 << 30)) < int((1 << 30) * most / n)))


def fit(stats: DataFrame, good: DataFrame, features: int = FEATURES) -> Model | None:
    """Fits on the chosen() rows among `stats`; None where there are none.

    Folds 1-3 give the ridge weights: each task sums the normal equations of its rows and the driver adds the sums.
    Fold 4 gives the calibration.
    """
    rows = common.stored(stats.join(good, F.col("doc_id") == F.col("id_")).select("doc_id", "quality", "stats", fold(F.col("doc_id")).alias("fold")))
    moments = rows.select("doc_id", F.posexplode("stats").alias("i", "v")).groupBy("i").agg(F.avg("v").alias("m"), F.stddev_pop("v").alias("s")).collect()
    if not moments:
        return None
    mean, std = np.zeros(_N), np.ones(_N)
    for r in moments:
        mean[r.i], std[r.i] = r.m, max(r.s, 1e-6)
    rng = np.random.default_rng(SEED)
    model = Model(mean, std, rng.normal(size=(_N, features)) / WIDTH, rng.uniform(0, 2 * np.pi, features), np.zeros(0), np.zeros(1), np.zeros(1))
    d = features + _N + 1

    def sums(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        a, k = np.zeros((d, d + 1)), 0
        for batch in batches:
            if batch.num_rows:
                x = model.features(np.array(batch.column("stats").to_pylist(), float))
                a += x.T @ np.hstack([x, batch.column("quality").to_numpy()[:, None]])
                k += len(x)
        if k:
            yield pa.RecordBatch.from_arrays([pa.array([a.tobytes()], pa.binary()), pa.array([k], pa.int64())], names=["a", "k"])

    a, k = np.zeros((d, d + 1)), 0
    for r in rows.filter("fold <> 4").coalesce(8).mapInArrow(sums, "a binary, k long").collect():
        a, k = a + np.frombuffer(bytes(r.a)).reshape(d, d + 1), k + r.k
    model.weights = np.linalg.solve(a[:, :d] + PENALTY * max(k, 1) * np.eye(d), a[:, d])
    held = rows.filter("fold = 4").select("stats", "quality").toPandas()
    if len(held) < 50:
        held = rows.select("stats", "quality").toPandas()
    model.x, model.y = isotonic(model.raw(np.array(held.stats.tolist(), float)), held.quality.to_numpy(float))
    return model


def score(stats: DataFrame, model: Model | None) -> DataFrame:
    """doc_id, held_out, score, predicted. Without a model (no labelled rows) every score is 0.5."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            s = model.scores(np.array(batch.column("stats").to_pylist(), float).reshape(-1, _N)) if model else np.full(batch.num_rows, 0.5)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(s)], names=["doc_id", "score"])

    return stats.mapInArrow(run, "doc_id long, score double").select("doc_id", (fold(F.col("doc_id")) == 0).alias("held_out"), "score", (F.col("score") >= CUTOFF).cast("int").alias("predicted"))


def classify(docs: DataFrame, labels: DataFrame, most: int = MOST_LABELLED) -> DataFrame:
    """Scores every document after fitting on `labels` (doc_id, quality).

    Columns used: doc_id, text. Null and empty texts have a score like any other; a null doc_id is scored and never
    learned from; rows with a null quality are left out; repeated rows are scored one by one.
    """
    stats = common.stored(statistics_of(docs))
    return score(stats, fit(stats, chosen(labels, most)))


def keep_good(docs: DataFrame, labels: DataFrame, most: int = MOST_LABELLED) -> DataFrame:
    """The rows of docs, all columns, that are predicted good.

    The fit takes statistics of the chosen documents only, `most` ids that are sent to the tasks. Rows alike go or stay
    alike; a null doc_id is judged like any other; without labels all rows stay; columns of any name are carried along.
    """
    good = chosen(labels, most)
    few = docs.select("doc_id", "text").join(F.broadcast(good.select("id_").distinct()), F.col("doc_id").cast("long") == F.col("id_"), "left_semi")  # at most about `most` ids
    model = fit(statistics_of(few), good)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in common.pieces(batches):
            s = model.scores(_stats_of(batch)) if model else np.full(batch.num_rows, 0.5)
            yield batch.filter(pa.array(s >= CUTOFF))

    return docs.mapInArrow(run, docs.schema)


def op4_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    return classify(common.table(spark, sf_dir, "documents"), common.table(spark, sf_dir, "labels"))
