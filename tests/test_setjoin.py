"""The exact set join against all pairs."""

import random

import pytest
from textmill.operators import dedup
from textmill.plans import setjoin


def corpus(n=160):
    """Texts of which many are copies, near copies, shares of one passage, short or empty."""
    rng = random.Random(5)
    word = lambda: f"w{rng.randrange(400)}"
    passage, near = [word() for _ in range(60)], [word() for _ in range(90)]
    out = []
    for k in range(n):
        w = [word() for _ in range(rng.randrange(5, 60))]
        if k % 4 == 0:
            w = near[: rng.randrange(60, 90)] + w[: rng.randrange(6)]
        elif k % 4 == 1:
            w = passage + w[: rng.randrange(40)]
        elif k % 8 == 2:
            w = out[rng.randrange(len(out))].lower().split()
        elif k % 8 == 6:
            w = [["a"], ["a", "b"], []][k % 3]
        out.append("  ".join(w).title())
    return [(1000 - 3 * k, None if k == 17 else t) for k, t in enumerate(out)]


def brute(rows, least):
    sets = {}
    for i, t in rows:
        w = (t or "").lower().split()
        s = {tuple(w[k : k + 8]) for k in range(len(w) - 7)} if len(w) >= 8 else {tuple(w)} if w else set()
        sets[i] = frozenset(s)
    same = {}
    for i, s in sets.items():
        if s:
            same.setdefault(s, []).append(i)
    first = {min(v): s for s, v in same.items()}
    sim = lambda x, y: round(len(x & y) / len(x | y), 6)
    pairs = {(a, b): sim(x, y) for a, x in first.items() for b, y in first.items() if a < b and sim(x, y) >= least}
    return pairs, {(i, min(v)) for v in same.values() for i in v if i != min(v)}, sets


@pytest.mark.parametrize("least, block, dense, chunk", [(0.5, 1000, 32, 4_000_000), (0.5, 7, 3, 300), (0.8, 7, 40, 50)])
def test_join_equals_all_pairs(spark, monkeypatch, least, block, dense, chunk):
    for name, v in (("BLOCK", block), ("DENSE", dense), ("CHUNK", chunk)):
        monkeypatch.setattr(setjoin, name, v)
    rows = corpus()
    pairs, members = dedup.jaccard_join(spark.createDataFrame(rows, "doc_id long, text string").repartition(3), least)
    want, of, _ = brute(rows, least)
    got = pairs.collect()
    assert len(got) == len(want) > 20 and {(r.src, r.dst): r.jaccard for r in got} == want
    assert {(r.id, r["first"]) for r in members.collect()} == of and of


def test_a_full_table_of_levels_leaves_nothing_out(spark, monkeypatch):
    monkeypatch.setattr(setjoin, "TABLE_BITS", 9)
    rows = corpus(80)
    pairs, _ = dedup.jaccard_join(spark.createDataFrame(rows, "doc_id long, text string"), 0.5)
    assert {(r.src, r.dst): r.jaccard for r in pairs.collect()} == brute(rows, 0.5)[0]


def test_copies_are_not_expanded_into_pairs(spark, tmp_path):
    text = " ".join(f"w{k}" for k in range(30))
    spark.createDataFrame([(k, text) for k in range(20)] + [(30, text + " end")], "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    rows = dedup._jaccard(spark, str(tmp_path)).collect()
    assert sorted((r.src, r.dst) for r in rows) == [*((0, k) for k in range(1, 20)), (0, 30)]


def test_recall_counts_copies_without_their_pairs(spark, tmp_path, monkeypatch):
    import duckdb
    from textmill import registry

    rows = corpus(100) + [(5000 + k, "one text of which there are many copies in the table") for k in range(30)]
    spark.createDataFrame(rows, "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    seen, join = [], dedup.candidates
    monkeypatch.setattr(dedup, "candidates", lambda keys: seen.append(keys.filter("doc_id > 5000").count()) or join(keys))
    got = registry.QUERIES["lsh_recall"](spark, str(tmp_path)).first().asDict()
    c = duckdb.connect()
    c.execute(f"CREATE VIEW documents AS SELECT doc_id, text FROM '{tmp_path}/documents.parquet/*.parquet'")
    cur = c.execute(registry.ORACLE["lsh_recall"])
    assert got == dict(zip([x[0] for x in cur.description], cur.fetchone())) and got["n_true"] > 435 and seen == [0]
