"""The pipeline's stages on the given tables."""

import random

import corpus_pipeline
from textmill.llm import simhash


def test_stages(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    assert len(corpus_pipeline.STAGES) == 5
    for name, stage in corpus_pipeline.STAGES[:4]:
        out = stage(spark, docs, sf)
        assert out.columns == docs.columns, name
        docs = out
    assert docs.count() > 0


def test_near_dedup_equals_brute_force(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    texts = {r.doc_id: r.text for r in docs.collect()}
    sets = {i: frozenset(tuple(w[k : k + 5]) for k in range(max(len(w) - 4, 1))) for i, w in ((i, t.lower().split()) for i, t in texts.items())}
    comp = {i: i for i in sets}
    for _ in range(3):
        for a in sets:
            for b in sets:
                if a < b and len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b]):
                    comp[a] = comp[b] = min(comp[a], comp[b])
    kept = {r.doc_id for r in simhash.keep_one(docs).select("doc_id").collect()}
    assert kept == {i for i, c in comp.items() if i == c}


def test_near_dedup_with_repeats_and_long_texts(spark):
    """Copies that repeat a passage have the same shingles; long texts just above and below the similarity are told apart."""
    rng = random.Random(7)
    word = lambda: f"w{rng.randint(0, 10**9)}"
    texts, kept = [], []
    for _ in range(30):
        w = [word() for _ in range(100)]
        kept.append(len(texts))
        texts += [" ".join(w), " ".join(w + w[10:25] * 12)]
    for new in (325, 331, 334, 340) * 4:
        w = [word() for _ in range(3000)]
        other = w[:1000] + [word() for _ in range(new - 4)] + w[1000 + new - 4 :]
        a, b = ({tuple(x[k : k + 5]) for k in range(len(x) - 4)} for x in (w, other))
        kept += [len(texts)] + [len(texts) + 1] * (len(a & b) < 0.8 * len(a | b))
        texts += [" ".join(w), " ".join(other)]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    assert sorted(r.doc_id for r in simhash.keep_one(docs).select("doc_id").collect()) == kept


def test_units_grow_less_than_the_square(spark):
    """Each two texts of a large shard meet in a unit that compares them, once; rows stay far below the square."""
    n, block = 400, 4
    got = simhash._units(spark.range(n).selectExpr("7L AS key", "id AS t", "id AS root"), block).collect()
    assert len(got) == n * 10
    units = {}
    for r in got:
        units.setdefault(r.key, []).append((r.t, r.side))
    met = sorted((a, b) for u in units.values() for a, x in u for b, y in u if a < b and (x != y or x == 2))
    assert met == [(a, b) for a in range(n) for b in range(a + 1, n)]


def test_run(spark, sf):
    out = corpus_pipeline.run(spark, sf)
    assert out.columns == ["doc_id", "start", "n_tokens", "ids_crc32"]
    rows = sorted((r.start, r.n_tokens) for r in out.collect())
    assert all(a + n == b for (a, n), (b, _) in zip(rows, rows[1:]))
