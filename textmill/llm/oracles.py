"""SQL that gives the same rows as a query, where SQL can."""

_SAID = "<|im_end|><|im_start|>assistant ok"
_ESCAPED = r"replace(replace({}, '\', '\\'), '<|', '<\|')"

CHAT = f"""WITH t AS (SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -1, 0, 'user', '{_SAID}' UNION ALL SELECT -1, 1, 'assistant', '{_SAID}')
SELECT conv_id, count(*) AS n_turns, sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn)) AS turns_sha256,
  coalesce(sum(length(text)) FILTER (role = 'assistant'), 0)::BIGINT AS loss_chars, sha256(coalesce(string_agg(text, '' ORDER BY turn) FILTER (role = 'assistant'), '')) AS loss_sha256,
  sum(24 + length(replace({_ESCAPED.format('role')}, chr(10), '<\\~')) + length({_ESCAPED.format('text')}))::BIGINT AS formatted_chars FROM t GROUP BY conv_id"""

PASSAGES = r"""WITH d AS MATERIALIZED (SELECT doc_id, list_filter(string_split_regex(coalesce(text, ''), '[ \t\n\x0B\f\r]+'), lambda x: x <> '') AS w FROM documents),
w AS MATERIALIZED (SELECT doc_id, i, md5(array_to_string(w[i:i + 34], ' ')) AS h FROM (SELECT doc_id, w, unnest(range(1, len(w) - 33)) AS i FROM d WHERE len(w) >= 35)),
gone AS MATERIALIZED (SELECT DISTINCT doc_id, unnest(range(i, i + 35)) AS i FROM w SEMI JOIN (SELECT h FROM w GROUP BY h HAVING count(*) > 1) USING (h)),
each AS (SELECT doc_id, unnest(w) AS word, unnest(range(1, len(w) + 1)) AS i FROM d),
kept AS (SELECT doc_id, count(*) AS n, string_agg(word, ' ' ORDER BY i) AS t FROM each ANTI JOIN gone USING (doc_id, i) GROUP BY doc_id)
SELECT doc_id, len(w)::BIGINT AS n_words, (len(w) - coalesce(n, 0))::BIGINT AS n_removed, sha256(coalesce(t, '')) AS kept_sha256 FROM d LEFT JOIN kept USING (doc_id)"""


def _mixed(x: str, i: int) -> str:
    """One step of the hash of a gram: common.mixed() in SQL."""
    if i < 2:
        return f"((xor({x}, {x} >> {(30, 27)[i]})::UHUGEINT * {(0xBF58476D1CE4E5B9, 0x94D049BB133111EB)[i]}) % 18446744073709551616)::UBIGINT"
    return f"xor({x}, {x} >> 31)"


#: Repeated strings of 400 bytes, and the 120 bytes behind each sampled place (the least gram of some 160).
REPEATS = rf"""WITH d AS MATERIALIZED (SELECT doc_id, hex(encode(coalesce(text, ''))) AS x FROM documents),
w AS MATERIALIZED (SELECT doc_id, i, md5_number(substr(x, 2 * i + 1, 800)) AS h FROM (SELECT doc_id, x, unnest(range(0, length(x) // 2 - 399)) AS i FROM d WHERE length(x) >= 800)),
s AS (SELECT doc_id, i FROM w SEMI JOIN (SELECT h FROM w GROUP BY h HAVING count(*) > 1) USING (h)),
g AS (SELECT doc_id, i, sum(CASE WHEN i > last + 400 OR last IS NULL THEN 1 ELSE 0 END) OVER (PARTITION BY doc_id ORDER BY i) AS run FROM (SELECT doc_id, i, lag(i) OVER (PARTITION BY doc_id ORDER BY i) AS last FROM s)),
r AS MATERIALIZED (SELECT doc_id, min(i) AS a, max(i) + 400 AS b FROM g GROUP BY doc_id, run),
k AS (SELECT doc_id, string_agg(substr(x, 2 * a + 1, 2 * (b - a)), '' ORDER BY a) AS t FROM (SELECT doc_id, x, b AS a, coalesce(lead(a) OVER (PARTITION BY doc_id ORDER BY a), length(x) // 2) AS b
  FROM (SELECT doc_id, a, b FROM r UNION ALL SELECT doc_id, -1, 0 FROM d) JOIN d USING (doc_id)) GROUP BY doc_id),
m0 AS (SELECT doc_id, i, ('0x' || substr(x, 2 * i + 1, 16))::UBIGINT AS g FROM (SELECT doc_id, x, unnest(range(0, length(x) // 2 - 7)) AS i FROM d WHERE length(x) >= 334)),
m1 AS (SELECT doc_id, i, {_mixed('g', 0)} AS g FROM m0), m2 AS (SELECT doc_id, i, {_mixed('g', 1)} AS g FROM m1), m3 AS (SELECT doc_id, i, {_mixed('g', 2)} AS g FROM m2),
p AS (SELECT DISTINCT doc_id, i FROM (SELECT doc_id, count(*) OVER v AS n, (min((g >> 27 << 27) + i::UBIGINT) OVER v % 134217728)::BIGINT AS i FROM m3 WINDOW v AS (PARTITION BY doc_id ORDER BY i ROWS BETWEEN CURRENT ROW AND 159 FOLLOWING)) WHERE n = 160),
q AS MATERIALIZED (SELECT doc_id, i, md5_number(substr(x, 2 * i + 1, 240)) AS h FROM p JOIN d USING (doc_id) WHERE length(x) >= 2 * (i + 120)),
u AS (SELECT doc_id, i AS a, i + 120 AS b FROM q SEMI JOIN (SELECT h FROM q GROUP BY h HAVING count(*) > 1) USING (h) UNION ALL SELECT doc_id, a, b FROM r),
y AS (SELECT doc_id, sum(greatest(0, b - greatest(a, coalesce(last, 0)))) AS n FROM (SELECT doc_id, a, b, max(b) OVER (PARTITION BY doc_id ORDER BY a, b ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS last FROM u) GROUP BY doc_id)
SELECT doc_id, (length(x) // 2)::BIGINT AS n_bytes, coalesce((SELECT sum(b - a) FROM r WHERE r.doc_id = d.doc_id), 0)::BIGINT AS n_removed, (SELECT count(*) FROM r WHERE r.doc_id = d.doc_id) AS n_spans,
  coalesce((SELECT n FROM y WHERE y.doc_id = d.doc_id), 0)::BIGINT AS n_shared, sha256(unhex(coalesce(t, ''))) AS kept_sha256
FROM d LEFT JOIN k USING (doc_id)"""
