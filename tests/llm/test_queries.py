"""The opN_ queries that SQL can't express, against brute force written from their contracts."""

import hashlib
import math
import re
import string
from collections import Counter, defaultdict

import pytest
import xxhash

from textmill.llm import registry

WORD = re.compile(r"[^\x20\x09-\x0D]+")


@pytest.fixture(scope="module")
def documents(spark, sf):
    return spark.read.parquet(f"{sf}/documents.parquet").collect()


def rows_of(spark, sf, name):
    return registry.QUERIES[name](spark, sf).collect()


def test_op1_targets_and_shares(spark, sf, documents):
    got = {r.doc_id: r for r in rows_of(spark, sf, "op1_mixing")}
    size = {r.doc_id: len(WORD.findall(r.text or "")) for r in documents}
    of = defaultdict(list)
    for r in documents:
        of[r.source].append(r.doc_id)
    sources = sorted((s for s in of if s is not None), key=lambda s: [ord(c) for c in s]) + ([None] if None in of else [])
    held = {s: sum(size[i] for i in of[s]) for s in sources}
    weight, total, full = {s: i % 3 + 1 for i, s in enumerate(sources)}, sum(held.values()), set()
    while True:
        left = total - sum(3 * held[s] for s in full)
        open_ = [s for s in sources if s not in full]
        target = {s: 3 * held[s] if s in full else left * weight[s] / sum(weight[o] for o in open_) for s in sources}
        over = {s for s in open_ if target[s] > 3 * held[s] + 1e-9}
        if not over:
            break
        full |= over
    assert len(got) == len(documents)
    for s in sources:
        for i in of[s]:
            assert got[i]["size"] == size[i] and got[i].source_size == held[s] and math.isclose(got[i].target, target[s], rel_tol=1e-9)
            assert got[i].taken <= 3 * size[i] and (size[i] == 0 or got[i].taken % size[i] == 0)
        longest = max(size[i] for i in of[s])
        assert abs(sum(got[i].taken for i in of[s]) - target[s]) <= max(0.03 * target[s], longest)
    assert {i: r.taken for i, r in got.items()} == {r.doc_id: r.taken for r in rows_of(spark, sf, "op1_mixing")}


def test_op5_all_alignments(spark, sf, documents):
    def clean(t):
        return [w for w in (x.strip(string.punctuation) for x in WORD.findall((t or "").lower())) if w]

    items = {r.item_id: clean(r.text) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()}
    want = set()
    for r in documents:
        h, places = clean(r.text), defaultdict(list)
        for k, w in enumerate(h):
            places[w].append(k)
        for i, w in items.items():
            hits = Counter(k - j for j, x in enumerate(w) for k in places.get(x, ()))
            least = min(13, len(w))
            for s, n in hits.items():
                if n < 0.8 * least:
                    continue
                ok = [0 <= s + j < len(h) and h[s + j] == x for j, x in enumerate(w)]
                a, b = max(0, -s), min(len(w), len(h) - s)
                if any(sum(ok[x:y]) >= 0.8 * (y - x) - 1e-9 for x in range(a, b) for y in range(x + least, b + 1)):
                    want.add((r.doc_id, i))
    got = {(r.doc_id, i) for r in rows_of(spark, sf, "op5_decontaminate") for i in r.item_ids}
    assert got == want and want


def test_op6_spans(spark, sf, documents):
    assign = re.compile(r"""((?i:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""")
    value = re.compile(r"[A-Za-z0-9+/_=-]{20,}")
    base, other, owners, places = {}, {}, defaultdict(set), defaultdict(set)
    for r in documents:
        t, found = r.text or "", []
        found += [(m.start(), 0, m.end(), m[2]) for m in assign.finditer(t) if len(m[2]) >= 8]
        found += [(m.start(), 1, m.end(), m[0]) for m in re.finditer(r"AKIA[A-Z0-9]+", t) if len(m[0]) >= 16]
        found += [(m.start(), 2, m.end(), m[0]) for m in re.finditer(r"[0-9a-f]+", t) if len(m[0]) >= 32]
        base[r.doc_id] = sorted(found)
        looks = [(m.start(), 3, m.end(), m[0]) for m in value.finditer(t) if all(re.search(p, m[0]) for p in ("[0-9]", "[A-Z]", "[a-z]"))]
        other[r.doc_id] = [x for x in looks if not any(b[0] < x[2] and x[0] < b[2] for b in found)]
        for x in base[r.doc_id] + other[r.doc_id]:
            owners[x[3]].add(r.source)
            places[x[3]].add((r.source, r.lang))
    kinds = ("assign", "access", "hex", "owned")
    text = lambda spans: ",".join(f"{kinds[s[1]]}:{s[0]}:{s[2]}" for s in spans)
    got = rows_of(spark, sf, "op6_secret_scan")
    assert len(got) == len(documents)
    for r in got:
        b = base[r.doc_id]
        assert (r.n_assign, r.n_access, r.n_hex) == tuple(sum(s[1] == k for s in b) for k in range(3))
        assert r.base_sha256 == hashlib.sha256(text(b).encode()).hexdigest()
        live = [s for s in other[r.doc_id] if len(owners[s[3]]) <= 1 and len(places[s[3]]) <= 2]
        assert r.spans == text(sorted(b + live))


def test_op7_verdicts(spark, sf, documents):
    lower = str.maketrans(string.ascii_uppercase, string.ascii_lowercase)
    kinds = {**dict.fromkeys(string.ascii_lowercase, "a"), **dict.fromkeys(string.ascii_uppercase, "A"), **dict.fromkeys(string.digits, "0"), **dict.fromkeys(" \t", " "), **dict.fromkeys("\n\r", "\n"), **dict.fromkeys(".,;:", "."), **dict.fromkeys("-_", "-"), **dict.fromkeys("'\"`()", "'"), **dict.fromkeys("!?", "!"), **dict.fromkeys("#*$%&|<>@=+/\\^~{}[]", "#")}
    classes = lambda t: Counter(kinds.get(c, "other" if ord(c) < 128 else "beyond") for c in t)
    words = lambda t: WORD.findall(t.translate(lower))

    def distance(p, q):
        n, m, out = sum(p.values()), sum(q.values()), 0.0
        if not n or not m:
            return 0.0
        for k in set(p) | set(q):
            a, b = p[k] / n, q[k] / m
            out += (a * math.log2(2 * a / (a + b)) if a else 0) + (b * math.log2(2 * b / (a + b)) if b else 0)
        return math.sqrt(max(out / 2, 0))

    char_ref, word_ref = defaultdict(Counter), defaultdict(Counter)
    for r in documents:
        char_ref[r.lang].update(classes(r.text))
        word_ref[r.lang].update(words(r.text))
    top = {lang: dict(sorted(c.items(), key=lambda x: (-x[1], x[0].encode()))[:100]) for lang, c in word_ref.items()}
    folded = lambda c, lang: Counter({w: n for w, n in c.items() if w in top[lang]} | {None: sum(n for w, n in c.items() if w not in top[lang])})
    text = {r.doc_id: r for r in documents}
    for r in rows_of(spark, sf, "op7_quality_rules"):
        t, lang = text[r.doc_id].text, text[r.doc_id].lang
        w = WORD.findall(t)
        seen = Counter(tuple(w[i : i + 5]) for i in range(len(w) - 4))
        cover = {i + k for i in range(len(w) - 4) if seen[tuple(w[i : i + 5])] > 1 for k in range(5)}
        lines = [x for x in t.split("\n") if WORD.search(x)]
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == (len(w), sum(map(len, w)), sum(c in "#*$%&|<>" for c in t), len(lines) - len(set(lines)), len(cover))
        assert r.base_failed == (len(w) < 10 or 100 * len(cover) > 20 * len(w))
        a, b = distance(classes(t), char_ref[lang]), distance(folded(Counter(words(t)), lang), folded(word_ref[lang], lang))
        assert abs(a - r.class_distance) < 1e-6 and abs(b - r.word_distance) < 1e-6
        assert r.kept == (not r.base_failed and (len(w) < 50 or (r.class_distance <= 0.30 and r.word_distance <= 0.50)))


def test_op8_components(spark, sf, documents):
    lower = bytes.maketrans(string.ascii_uppercase.encode(), string.ascii_lowercase.encode())
    prints = {}
    for r in documents:
        w = [x.encode().translate(lower) for x in WORD.findall(r.text or "")]
        shingles = [b" ".join(w[i : i + 3]) for i in range(max(len(w) - 2, 1))] if w else []
        h = [xxhash.xxh64_intdigest(s, seed=42) for s in shingles]
        prints[r.doc_id] = sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))
    comp, ids = {i: i for i in prints}, sorted(prints)
    changed = True
    while changed:
        changed = False
        for a in ids:
            for b in ids:
                if comp[a] < comp[b] and (prints[a] ^ prints[b]).bit_count() <= 3:
                    comp[b], changed = comp[a], True
    got = rows_of(spark, sf, "op8_simhash")
    assert {r.doc_id: (r.fingerprint, r.component_id) for r in got} == {i: (f"{prints[i]:016x}", comp[i]) for i in ids}


def test_op4_held_out(spark, sf):
    labels = {r.doc_id: r.quality for r in spark.read.parquet(f"{sf}/labels.parquet").collect()}
    got = rows_of(spark, sf, "op4_quality_classifier")
    held = [(r.score, r.predicted, labels[r.doc_id]) for r in got if r.held_out and r.doc_id in labels]
    assert all(r.predicted == int(r.score >= 0.3) for r in got)
    assert sum(p == q for _, p, q in held) >= 0.9 * len(held) and len({q for *_, q in held}) == 2
