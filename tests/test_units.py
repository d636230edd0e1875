"""Worked examples, brute force and invariants."""

import random
from collections import Counter

import numpy as np
from pyspark.sql import functions as F

from textmill.functions.text import ARABIC, normalize_script
from textmill.operators import dedup, evaluation, mixture, more, quality, retrieval, tokenizer
from textmill.plans.components import connected_components
from textmill.plans.prefixsum import prefix_sum


def naive_bpe(pieces, merges):
    seqs, out = [(list(p), c) for p, c in pieces], []
    for _ in range(merges):
        n = Counter()
        for q, c in seqs:
            for pair in zip(q, q[1:]):
                n[pair] += c
        if not n:
            break
        best = min(n, key=lambda p: (-n[p], p))
        out.append((*best, n[best]))
        new = []
        for q, c in seqs:
            r, i = [], 0
            while i < len(q):
                if i + 1 < len(q) and (q[i], q[i + 1]) == best:
                    r.append(q[i] + q[i + 1])
                    i += 2
                else:
                    r.append(q[i])
                    i += 1
            new.append((r, c))
        seqs = new
    return out


def test_bpe_equals_naive():
    rng = random.Random(3)
    for _ in range(20):
        pieces = [("".join(rng.choice("abc") for _ in range(rng.randint(1, 8))), rng.randint(1, 5)) for _ in range(12)]
        assert tokenizer.bpe_train(pieces, 10) == naive_bpe(pieces, 10)


def test_merges_made_at_once_are_those_made_one_by_one():
    rng = random.Random(8)
    for _ in range(60):
        pieces = [("".join(rng.choice("abcdefgh") for _ in range(rng.randint(1, 9))), rng.randint(1, 4)) for _ in range(rng.randint(3, 40))]
        want, got, q = naive_bpe(pieces, 25), [], [(list(p), c) for p, c in pieces]
        while len(got) < 25:
            n = Counter()
            for s, c in q:
                for pair in zip(s, s[1:]):
                    n[pair] += c
            top = sorted(((a, b, m) for (a, b), m in n.items()), key=lambda x: (-x[2], x[0], x[1]))
            cut = rng.randint(1, 12)
            batch = tokenizer.safe_prefix(top[:cut], 25 - len(got), len(top) <= cut)
            if not batch:
                break
            got += batch
            for a, b, _ in batch:
                q = [(tokenizer._joined(s, (a, b)), c) for s, c in q]
        assert got == want


def test_training_in_rounds(spark):
    rng = random.Random(9)
    pieces = Counter("".join(rng.choice("abcdefghij") for _ in range(rng.randint(1, 9))) for _ in range(300))
    df = spark.createDataFrame(list(pieces.items()), "word string, cnt long").repartition(3)
    assert tokenizer.bpe_train_rounds(df, 12, top=50) == naive_bpe(sorted(pieces.items()), 12)


def test_training_in_few_rounds_equals_naive(spark, monkeypatch):
    rng, jobs = random.Random(4), []
    count = tokenizer.reliable
    monkeypatch.setattr(tokenizer, "reliable", lambda df: jobs.append(1) or count(df))
    for letters, top, most in (("abcdefghijklmnop", 60, 10_000), ("abc", 5, 40), ("aab", 3, 2), ("ab\U0001d4b3é", 2, 10_000)):
        pieces = Counter("".join(rng.choice(letters) for _ in range(rng.randint(1, 12))) for _ in range(250))
        df = spark.createDataFrame(list(pieces.items()), "word string, cnt long").repartition(2)
        before = len(jobs)
        assert tokenizer.bpe_train_rounds(df, 14, top=top, most=most) == naive_bpe(sorted(pieces.items()), 14)
        assert top < 60 or len(jobs) - before <= 8  # two tables a round at most, and few rounds


def test_encode_joins_to_word_and_stops_at_vocab():
    pieces = [("banana", 5), ("bandana", 3)]
    merges = tokenizer.bpe_train(pieces, vocab=8)
    assert len(merges) == 8 - len(set("banandana"))
    ranks = {(a, b): i for i, (a, b, _) in enumerate(merges)}
    assert "".join(tokenizer.bpe_encode("bananas", ranks)) == "bananas"


def test_bounded_tokens_stay_inside_morphemes():
    ranks = {(a, b): i for i, (a, b, _) in enumerate(tokenizer.bpe_train([("ver", 9), ("steh", 9), ("en", 9)], 20))}
    for w in ("verstehen", "versteher"):
        m = tokenizer.affix_segments(w)
        assert "".join(m) == w
        t = [x for p in m for x in tokenizer.bpe_encode(p, ranks)]
        ends = {sum(map(len, m[: i + 1])) for i in range(len(m))}
        assert ends <= {sum(map(len, t[: i + 1])) for i in range(len(t))}


def test_alignment_examples():
    assert tokenizer.alignment(["wbi", "kitab", "him"], ["w", "bi", "kitab", "him"]) == 0.5
    assert tokenizer.alignment(["a", "b"], ["a", "b"]) == 1.0
    assert tokenizer.alignment(["ab"], ["a", "b"], "distance") == 3
    assert tokenizer.boundary_f1(["ab", "c"], ["ab", "c"]) == 1.0


def test_word_errors():
    assert evaluation.word_errors("a b c".split(), "a x c d".split()) == 2


def test_bucket_plan():
    assert dedup.plan_buckets(100e12)[0] == 6667


def test_golden_candidates(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    sig = dedup.minhash_signatures(docs).cache()
    assert dedup.candidates(dedup.band_keys(sig)).count() == 96
    assert dedup.verified(dedup.candidates(dedup.band_keys(sig)), docs).count() == 94
    assert dedup.fuzzy(docs).count() == 926


def test_components_of_a_chain(spark):
    e = spark.range(0, 50).select(F.col("id").alias("src"), (F.col("id") + 1).alias("dst"))
    got = connected_components(e).collect()
    assert len(got) == 51 and {r.comp for r in got} == {0}


def test_prefix_sum(spark):
    got = {r.id: r.s for r in prefix_sum(spark.range(100).repartition(7), ["id"], F.col("id"), "s", 5).collect()}
    assert got == {i: i * (i - 1) // 2 for i in range(100)}


def test_packing_conserves_tokens(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    rows = mixture.pack(docs, 512).groupBy("seq_id").agg(F.sum(F.col("to_tok") - F.col("from_tok")).alias("n")).orderBy("seq_id").collect()
    assert all(r.n == 512 for r in rows[:-1])
    assert sum(r.n for r in rows) == mixture.with_tokens(docs).agg(F.sum("tokens")).first()[0]


def test_script_profile(spark):
    text = "أَكـتب ١۲"
    got = spark.createDataFrame([(text,)], "t string").select(normalize_script(F.col("t"), ARABIC)).first()[0]
    assert got == "اكتب 12"


def test_signals_of_edge_rows(spark):
    rows = [(1, ""), (2, None), (3, "word"), (4, "..."), (5, "سؤال؟ جواب.\nسطر")]
    got = {r.doc_id: r for r in quality.signals(spark.createDataFrame(rows, "doc_id long, text string"), ARABIC).collect()}
    assert got[1].n_words == got[2].n_words == 0
    assert got[5].n_sentences == 2 and got[5].target_script_frac == 1.0
    one = "x" * 250
    df = spark.createDataFrame([(1, f"{one}\nshort\nshort")], "doc_id long, text string")
    assert quality.paragraph_rule(df).count() == 0


def test_dedup_is_idempotent(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    once = dedup.exact(docs, dedup.normal(F.col("text")))
    assert dedup.exact(once, dedup.normal(F.col("text"))).count() == once.count()


def test_linked_goes_on_where_stars_fail(spark):
    """Buckets of chains: only the neighbours of a chain are alike, and a star links none or few of them."""
    chain = [(i, 0, "a") for i in (1, 2, 3)] + [(i, 0, "b") for i in range(10, 30)] + [(i, 1, "b") for i in range(10, 30, 2)] + [(40, 0, "c"), (41, 0, "c")]
    bk = spark.createDataFrame(chain, "doc_id long, band int, key string")
    like = lambda pairs: pairs.filter("dst - src = 1 and src < 39")
    got = {r.id: r.comp for r in dedup._linked(bk, like).collect()}
    assert got == {1: 1, 2: 1, 3: 1} | dict.fromkeys(range(10, 30), 10)


def test_fuzzy_keeps_one_of_drifting_copies(spark):
    """Of three texts the middle one is like both others, which are not like each other."""
    rng = random.Random(11)
    for seed in range(40):
        w = [f"w{rng.randint(0, 10**6)}" for _ in range(207)]
        a, b, c = (" ".join([f"x{seed}y{i}" for i in range(k)] + w[k:]) for k in (12, 0, 0))
        c = " ".join(w[:-12] + [f"z{seed}y{i}" for i in range(12)])
        docs = spark.createDataFrame([(1, a), (2, b), (3, c)], "doc_id long, text string").coalesce(1)
        keys = {r.doc_id: set(r.k) for r in dedup.band_keys(dedup.minhash_signatures(docs)).groupBy("doc_id").agg(F.collect_list(F.concat_ws("-", "band", "key")).alias("k")).collect()}
        if keys[1] & keys[2] & keys[3] and not (keys[2] & keys[3]) - keys[1]:
            assert dedup.fuzzy(docs).select("doc_id", "cluster_size").collect() == [(1, 3)]
            return
    raise AssertionError("no seed puts the three in one bucket")


def test_all_near_vectors_in_passes(spark, monkeypatch):
    """All pairs, none by chance, however the vectors are cut into passes; a group near one vector makes no square of edges."""
    rng = np.random.default_rng(3)
    x = rng.standard_normal((300, 64)).astype(np.float32)
    x[100:200] = x[100] + 0.3 * x[100:200]
    x[250:] = 0.62 * x[:50] + 0.78 * x[250:]  # about the threshold
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    e = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<float>")
    cos = np.round(x.astype(np.float64) @ x.astype(np.float64).T, 5)
    want = {(i, j) for i in range(300) for j in range(i + 1, 300) if cos[i, j] >= dedup.NEAR}
    assert len(want) > 4950
    for size in (32_000_000, 30_000):
        monkeypatch.setattr(dedup, "PASS_BYTES", size)
        monkeypatch.setattr(dedup, "SIDE", 64)
        assert {(r.src, r.dst) for r in dedup.all_near_vectors(e).collect()} == want
        edges = dedup.all_near_vectors(e, forest=True).coalesce(1)
        assert edges.count() < 3 * 4 * 300
        comp = {r.id: r.comp for r in dedup.connected_components(edges).collect()}
        own = {i: i for i in range(300)}
        for _ in range(10):
            for i, j in want:
                own[i] = own[j] = min(own[i], own[j])
        assert all(comp.get(i, i) == c for i, c in own.items())


def test_toxic_classifier_scores_all(spark, sf):
    from textmill import registry

    rows = {r.doc_id: r for r in registry.QUERIES["toxic_classifier"](spark, sf).collect()}
    assert set(rows) == {r.doc_id for r in spark.read.parquet(f"{sf}/documents.parquet").select("doc_id").collect()}
    labels = {r.doc_id: r.toxic for r in spark.read.parquet(f"{sf}/labels.parquet").collect()}
    assert all(0 <= r.score <= 1 and r.toxic == labels.get(i) for i, r in rows.items())


def test_closeness_reads_whole_texts(spark):
    head, tail = "plain words of one kind " * 100, "zqx jvk " * 400
    texts = [("en", head), ("fr", head + tail), ("fr", "aB" + tail), ("de", "été \U0001f600" + head)]
    docs = spark.createDataFrame([(i, lang, t) for i, (lang, t) in enumerate(texts)], "doc_id long, lang string, text string")
    grams = [Counter(t.lower()[k : k + 3] for k in range(len(t) - 2)) for _, t in texts]
    got = {r.doc_id: r.s for r in more.closeness(docs).collect()}
    for i, g in enumerate(grams):
        assert abs(got[i] - sum(c * grams[0][x] for x, c in g.items()) / sum(c * c for c in g.values()) ** 0.5) < 1e-5


def test_rag_prompt_holds_whole_texts(spark, sf):
    from textmill import registry

    texts = {r.doc_id: r.text for r in spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").collect()}
    fit = [(r.qid, r.cid) for r in retrieval.context_fit(spark, sf).collect()]
    prompts = {r.qid: r.prompt for r in registry.QUERIES["rag_prompt"](spark, sf).collect()}
    assert any(len(texts[c]) > 200 for _, c in fit)
    assert all(f"[{c}] {texts[c]}" in prompts[q] for q, c in fit)
