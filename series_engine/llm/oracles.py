"""SQL for the operators that SQL can express; the others are tested against plain versions."""

_SPACE = r"[\x20\x09-\x0D]"

_EXACT = f"""WITH d AS (SELECT doc_id, length(coalesce(text, '')) AS chars, regexp_replace(coalesce(text, ''), '{_SPACE}', '', 'g') AS n FROM documents)
SELECT doc_id, first_value(doc_id) OVER w AS keep_id, count(*) OVER (PARTITION BY n) AS group_size, row_number() OVER w = 1 AS kept, sha256(n) AS text_sha256
FROM d WINDOW w AS (PARTITION BY n ORDER BY chars DESC, doc_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)"""

_REPEATS = f"""WITH d AS (SELECT doc_id, list_filter(string_split_regex(coalesce(text, ''), '{_SPACE}+'), lambda w: w <> '') AS w FROM documents),
s AS (SELECT doc_id, unnest(range(1, greatest(len(w) - 11, 1))) AS i, w FROM d),
g AS (SELECT doc_id, i, array_to_string(w[i:i + 12], ' ') AS win FROM s),
m AS (SELECT win, min(doc_id) AS low FROM g GROUP BY win),
f AS (SELECT g.doc_id, g.i FROM g JOIN m ON m.win = g.win AND m.low < g.doc_id),
p AS (SELECT doc_id, unnest(range(1, len(w) + 1)) AS i, unnest(w) AS word FROM d),
q AS (SELECT p.doc_id, p.i, p.word, coalesce(max(CASE WHEN f.i IS NOT NULL THEN 1 ELSE 0 END) OVER (PARTITION BY p.doc_id ORDER BY p.i ROWS 12 PRECEDING), 0) AS gone FROM p LEFT JOIN f ON f.doc_id = p.doc_id AND f.i = p.i)
SELECT d.doc_id, CAST(len(d.w) AS BIGINT) AS n_words, CAST(coalesce(r.n, 0) AS BIGINT) AS n_removed, sha256(coalesce(r.kept, '')) AS kept_sha256
FROM d LEFT JOIN (SELECT doc_id, sum(gone) AS n, string_agg(word, ' ' ORDER BY i) FILTER (WHERE gone = 0) AS kept FROM q GROUP BY doc_id) r ON r.doc_id = d.doc_id"""

ORACLES: dict[str, str] = {"op3_exact_dedup": _EXACT, "op9_substring_dedup": _REPEATS}
