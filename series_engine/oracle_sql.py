"""SQL text for checks: series, words, splits and neighbours, in plain tables.

The engine never runs these; they say again, for a relational database, what its queries
return.
"""

from __future__ import annotations

from .functions.summaries import CAP, breakpoints, edges, midpoints
from .sources.builders import ALPHABET, LINE_ORDER, OWNER

_ORDER = ", ".join(LINE_ORDER)


def _list(values) -> str:
    return "[" + ", ".join("'Infinity'::DOUBLE" if v == float("inf") else "'-Infinity'::DOUBLE" if v == float("-inf") else f"{float(v)!r}::DOUBLE" for v in values) + "]"


def _text(n: int, step: str) -> str:
    return f"""t0 AS (SELECT doc_id, text, unnest(range(0, length(text) // {n})) AS k FROM documents),
t1 AS (SELECT doc_id * {OWNER} + k AS series_id, string_split(substring(text, k * {n} + 1, {n}), '') AS c FROM t0),
t2 AS (SELECT series_id, unnest(c) AS ch, generate_subscripts(c, 1) - 1 AS p FROM t1),
t3 AS (SELECT series_id, p, CAST(instr('{ALPHABET}', ch) AS DOUBLE) AS r FROM t2),
t4 AS (SELECT series_id, p, {step} AS step FROM t3),
t5 AS (SELECT series_id, p, sum(step) OVER (PARTITION BY series_id ORDER BY p) AS v FROM t4),
series AS (SELECT series_id, list(v ORDER BY p) AS vals FROM t5 GROUP BY series_id)"""


#: ``series(series_id, vals)`` of each stand-in, as the body of a WITH clause.
SERIES = {
    "vectors": "series AS (SELECT vec_id AS series_id, list_transform(embedding, lambda v: CAST(v AS DOUBLE)) AS vals FROM embeddings)",
    "walks": f"""w0 AS (SELECT l_suppkey, l_quantity - 25.5 AS step, row_number() OVER (PARTITION BY l_suppkey ORDER BY {_ORDER}) - 1 AS i FROM lineitem),
w1 AS (SELECT l_suppkey * {OWNER} + i // 64 AS series_id, i % 64 AS p, step FROM w0),
w2 AS (SELECT series_id, p, sum(step) OVER (PARTITION BY series_id ORDER BY p) AS v FROM w1),
series AS (SELECT series_id, list(v ORDER BY p) AS vals FROM w2 GROUP BY series_id HAVING count(*) = 64)""",
    "letters": _text(128, "r - avg(r) OVER (PARTITION BY series_id)"),
    "ramps": _text(256, "r - 10"),
    "pulses": f"""p0 AS (SELECT user_id, value, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) - 1 AS i FROM events),
p1 AS (SELECT user_id, count(*) AS n FROM p0 GROUP BY user_id HAVING count(*) >= 32),
p2 AS (SELECT user_id, unnest(range(0, (n - 32) // 4 + 1)) AS k FROM p1),
p3 AS (SELECT p2.user_id * {OWNER} + k AS series_id, p0.i - 4 * k AS p, value FROM p2 JOIN p0 ON p0.user_id = p2.user_id AND p0.i >= 4 * k AND p0.i < 4 * k + 32),
p4 AS (SELECT series_id, p, value - avg(value) OVER (PARTITION BY series_id) AS step FROM p3),
p5 AS (SELECT series_id, p, sum(step) OVER (PARTITION BY series_id ORDER BY p) AS v FROM p4),
series AS (SELECT series_id, list(v ORDER BY p) AS vals FROM p5 GROUP BY series_id)""",
    "monthly": """m0 AS (SELECT c_nationkey AS nation, (year(o_orderdate) - 1995) * 12 + month(o_orderdate) - 1 AS m, sum(o_totalprice) AS v FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY ALL),
m1 AS (SELECT n_nationkey AS nation, unnest(range(0, 64)) AS m FROM nation),
series AS (SELECT CAST(m1.nation AS BIGINT) AS series_id, list(coalesce(v, 0.0) ORDER BY m1.m) AS vals FROM m1 LEFT JOIN m0 ON m0.nation = m1.nation AND m0.m = m1.m GROUP BY 1)""",
}
LENGTH = {"vectors": 64, "walks": 64, "letters": 128, "ramps": 256, "pulses": 32, "monthly": 64}


def normal(name: str) -> str:
    """``z(series_id, z)``: normalised."""
    return SERIES[name] + """,
z0 AS (SELECT series_id, vals, list_avg(vals) AS mean FROM series),
z1 AS (SELECT series_id, vals, mean, list_avg(list_transform(vals, lambda x: (x - mean) * (x - mean))) AS var FROM z0),
z AS (SELECT series_id, CASE WHEN var > 1e-18 THEN list_transform(vals, lambda x: (x - mean) / sqrt(var)) ELSE list_transform(vals, lambda x: 0.0) END AS z FROM z1)"""


def words(name: str, w: int, bits: int = 8) -> str:
    """``paa(series_id, z, m)`` and ``words(series_id, z, m, s)``: segment means and symbols."""
    size = LENGTH[name] // w
    return normal(name) + f""",
paa AS (SELECT series_id, z, list_transform(range(0, {w}), lambda i: list_avg(z[i * {size} + 1:(i + 1) * {size}])) AS m FROM z),
words AS (SELECT series_id, z, m, list_transform(m, lambda v: len(list_filter({_list(breakpoints(bits))}, lambda b: b <= round(v, 9)))) AS s FROM paa)"""


def dashed(column: str) -> str:
    return f"array_to_string(list_transform({column}, lambda v: CAST(v AS VARCHAR)), '-')"


def held(limit: int = 200) -> str:
    """``q``: held-out rows of ``words``; ``c``: the collection."""
    return f"""q AS (SELECT * FROM words WHERE series_id % 25 = 7 ORDER BY series_id LIMIT {limit}), c AS (SELECT * FROM words WHERE series_id % 25 <> 7)"""


def asked(name: str, w: int = 8) -> str:
    """``q``: every row whose id is divisible by 50; ``c``: all rows."""
    return f"""{words(name, w)}, q AS (SELECT * FROM words WHERE series_id % 50 = 0), c AS (SELECT * FROM words)"""


def knn_all(name: str, k: int, where: str = "true") -> str:
    """k nearest of all rows for every row whose id is divisible by 50."""
    return f"""WITH {asked(name)},
d AS (SELECT q.series_id AS query_id, c.series_id, list_distance(q.z, c.z) AS distance FROM q CROSS JOIN c WHERE {where}),
r AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY distance, series_id) AS rank FROM d)
SELECT query_id, CAST(rank AS INTEGER) AS rank, series_id, round(distance, 6) AS distance FROM r WHERE rank <= {k}"""


def knn(name: str, k: int, limit: int, where: str = "true", w: int = 8) -> str:
    return f"""WITH {words(name, w)}, {held(limit)},
d AS (SELECT q.series_id AS query_id, c.series_id, list_distance(q.z, c.z) AS distance FROM q CROSS JOIN c WHERE {where}),
r AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY distance, series_id) AS rank FROM d)
SELECT query_id, CAST(rank AS INTEGER) AS rank, series_id, round(distance, 6) AS distance FROM r WHERE rank <= {k}"""


def level2(name: str, w: int, th: int, alpha: float = 0.2, f_low: float = 0.5, f_high: float = 3.0, source: str = "words", collection: str = "series_id % 25 <> 7") -> str:
    """The root's cells and the best plan of each full one.

    ``cells(cell, n)``, ``v(cell, seg, var, mean)``, ``base(cell, nb, n)``, ``sized(cell, mask, sid, n)``,
    ``scored(cell, mask, lam, score)``, ``best(cell, mask, lam)``.  In masks and cells the first segment is the highest bit.
    """
    bit = lambda b: f"list_sum(list_transform(range(1, {w + 1}), lambda i: ((s[i] >> {7 - b}) & 1) * (1 << ({w} - i))))"
    seg = ", ".join(f"({i}, {1 << (w - 1 - i)})" for i in range(w))
    return words(name, w) + f""",
x AS (SELECT series_id, z, m, s, CAST({bit(0)} AS BIGINT) AS cell, CAST({bit(1)} AS BIGINT) AS nb FROM {source}),
col AS (SELECT * FROM x WHERE {collection}),
cells AS (SELECT cell, count(*) AS n FROM col GROUP BY cell),
big AS (SELECT cell, n, greatest(1, CAST(ceil(log2(n / ({f_high} * {th})) - 1e-12) AS BIGINT)) AS lo, greatest(greatest(1, CAST(ceil(log2(n / ({f_high} * {th})) - 1e-12) AS BIGINT)), least({w}, CAST(floor(log2(n / ({f_low} * {th})) + 1e-12) AS BIGINT))) AS hi FROM cells WHERE n > {th}),
mids AS (SELECT cell, i - 1 AS seg, {_list(midpoints(8))}[s[i] + 1] AS mid FROM col, (SELECT unnest(range(1, {w + 1})) AS i) WHERE cell IN (SELECT cell FROM big)),
v AS (SELECT cell, seg, var_pop(mid) AS var, avg(mid) AS mean FROM mids GROUP BY cell, seg),
base AS (SELECT cell, nb, count(*) AS n FROM col WHERE cell IN (SELECT cell FROM big) GROUP BY cell, nb),
plans AS (SELECT mask, bit_count(mask) AS lam FROM (SELECT CAST(unnest(range(1, {1 << w})) AS BIGINT) AS mask)),
tried AS (SELECT big.cell, big.n, mask, lam FROM big JOIN plans ON lam BETWEEN lo AND hi),
sized AS (SELECT t.cell, t.mask, t.lam, t.n AS total, b.nb & t.mask AS sid, CAST(sum(b.n) AS BIGINT) AS n FROM tried t JOIN base b ON b.cell = t.cell GROUP BY ALL),
seg(seg, bit) AS (VALUES {seg}),
spread AS (SELECT t.cell, t.mask, exp(sqrt(avg(v.var))) AS e FROM tried t JOIN seg ON t.mask & seg.bit <> 0 JOIN v ON v.cell = t.cell AND v.seg = seg.seg GROUP BY t.cell, t.mask),
scored AS (SELECT s.cell, s.mask, s.lam, any_value(p.e) + {alpha} * exp(-(1 + count(*) FILTER (WHERE s.n > {th}) / (1 << s.lam)) * sqrt(greatest(0, sum((s.n / {th}) * (s.n / {th})) / (1 << s.lam) - pow(any_value(s.total) / {th} / (1 << s.lam), 2)))) AS score
FROM sized s JOIN spread p ON p.cell = s.cell AND p.mask = s.mask GROUP BY s.cell, s.mask, s.lam),
best AS (SELECT cell, mask, lam, score FROM (SELECT *, row_number() OVER (PARTITION BY cell ORDER BY round(score, 9) DESC, lam DESC, mask DESC) AS i FROM scored) WHERE i = 1)"""


def _bounds(name: str, w: int) -> tuple[str, str]:
    """Lower bounds of ``q.m`` from the root cell ``f.cell`` and from the leaf (``f.mask``, ``f.leaf``) in it."""
    n = LENGTH[name]
    gap = lambda lo, hi: f"pow(greatest({lo} - q.m[i], q.m[i] - {hi}, 0.0), 2)"
    one, two = _list(edges(1)), _list(edges(2))
    cell1 = f"((f.cell >> ({w} - i)) & 1)"
    cell2 = f"(2 * {cell1} + ((f.leaf >> ({w} - i)) & 1))"
    wide = f"sqrt({n / w} * list_sum(list_transform(range(1, {w + 1}), lambda i: {gap(f'{one}[{cell1} + 1]', f'{one}[{cell1} + 2]')})))"
    fine = f"sqrt({n / w} * list_sum(list_transform(range(1, {w + 1}), lambda i: CASE WHEN ((f.mask >> ({w} - i)) & 1) = 1 THEN {gap(f'{two}[{cell2} + 1]', f'{two}[{cell2} + 2]')} ELSE {gap(f'{one}[{cell1} + 1]', f'{one}[{cell1} + 2]')} END)))"
    return wide, fine


def placed(name: str, w: int, th: int, collection: str = "true") -> str:
    """``placed(series_id, z, cell, mask, leaf)``: leaves of the unpacked two-level tree."""
    return f"""{level2(name, w, th, collection=collection)},
placed AS (SELECT col.series_id, col.z, col.cell, coalesce(best.mask, 0) AS mask, coalesce(col.nb & best.mask, -1) AS leaf FROM col LEFT JOIN best ON best.cell = col.cell)"""


def leaf_search(name: str, w: int, th: int, k: int, leaves: int, how: str) -> str:
    """k nearest in ``leaves`` leaves of the two-level tree over all rows, for every row whose
    id is divisible by 50.  how: "extended" (around the query's place) or "budget" (own leaf,
    then by bound)."""
    wide, fine = _bounds(name, w)
    if how == "budget":
        chosen = f"chosen AS (SELECT query_id, cell, leaf FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY foreign_leaf, b, cell, leaf) AS i FROM leafbound) WHERE i <= {leaves})"
    else:
        chosen = f"""size AS (SELECT cell, count(*) AS m FROM f GROUP BY cell),
home AS (SELECT q.series_id AS query_id, q.cell, s.m FROM q JOIN size s ON s.cell = q.cell),
cells_in AS (SELECT c.query_id, c.cell, s.m, coalesce(sum(s.m) OVER (PARTITION BY c.query_id ORDER BY (c.cell <> h.cell), c.b, c.cell ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS ahead
FROM cellbound c JOIN home h ON h.query_id = c.query_id JOIN size s ON s.cell = c.cell WHERE h.m <= {leaves}),
chosen AS (SELECT query_id, cell, leaf FROM (SELECT l.query_id, l.cell, l.leaf, row_number() OVER (PARTITION BY l.query_id ORDER BY foreign_leaf, b, l.leaf) AS i FROM leafbound l JOIN home h ON h.query_id = l.query_id AND h.cell = l.cell WHERE h.m > {leaves}) WHERE i <= {leaves}
UNION ALL SELECT query_id, cell, leaf FROM (SELECT l.query_id, l.cell, l.leaf, c.m, c.ahead, row_number() OVER (PARTITION BY l.query_id, l.cell ORDER BY b, l.leaf) AS i FROM leafbound l JOIN cells_in c ON c.query_id = l.query_id AND c.cell = l.cell WHERE c.ahead < {leaves}) WHERE ahead + m <= {leaves} OR i <= {leaves} - ahead)"""
    return f"""WITH {placed(name, w, th)},
q AS (SELECT series_id, z, m, cell, nb FROM x WHERE series_id % 50 = 0),
f AS (SELECT DISTINCT cell, mask, leaf FROM placed),
cellbound AS (SELECT q.series_id AS query_id, f.cell, min({wide}) AS b FROM q CROSS JOIN (SELECT DISTINCT cell FROM f) f GROUP BY ALL),
leafbound AS (SELECT q.series_id AS query_id, f.cell, f.leaf, {fine} AS b, NOT (q.cell = f.cell AND (f.leaf = -1 OR q.nb & f.mask = f.leaf)) AS foreign_leaf FROM q CROSS JOIN f),
{chosen},
d AS (SELECT o.query_id, p.series_id, list_distance(q.z, p.z) AS distance FROM chosen o JOIN q ON q.series_id = o.query_id JOIN placed p ON p.cell = o.cell AND p.leaf = o.leaf),
r AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY distance, series_id) AS rank FROM d)
SELECT query_id, CAST(rank AS INTEGER) AS rank, series_id, round(distance, 6) AS distance FROM r WHERE rank <= {k}"""


def leaf_widths(w: int, n: int) -> str:
    """Upper bound of the leaf (``f.cell``, ``f.mask``, ``f.leaf``), open cells closed at the cap."""
    one, two = _list(edges(1, CAP)), _list(edges(2, CAP))
    cell1 = f"((f.cell >> ({w} - i)) & 1)"
    cell2 = f"(2 * {cell1} + ((f.leaf >> ({w} - i)) & 1))"
    return f"sqrt({n / w} * list_sum(list_transform(range(1, {w + 1}), lambda i: pow(CASE WHEN ((f.mask >> ({w} - i)) & 1) = 1 THEN {two}[{cell2} + 2] - {two}[{cell2} + 1] ELSE {one}[{cell1} + 2] - {one}[{cell1} + 1] END, 2))))"


def one_leaf(name: str, w: int, th: int, k: int, limit: int) -> str:
    """k nearest in the query's leaf of the unpacked two-level tree.  Where its cell is empty,
    the sibling with the least lower bound stands in, and below a full sibling its best leaf."""
    n = LENGTH[name]
    gap = lambda lo, hi: f"pow(greatest({lo} - q.m[i], q.m[i] - {hi}, 0.0), 2)"
    one, two = _list(edges(1)), _list(edges(2))
    cell1 = f"((f.cell >> ({w} - i)) & 1)"
    cell2 = f"(2 * {cell1} + ((f.leaf >> ({w} - i)) & 1))"
    wide = f"sqrt({n / w} * list_sum(list_transform(range(1, {w + 1}), lambda i: {gap(f'{one}[{cell1} + 1]', f'{one}[{cell1} + 2]')})))"
    fine = f"sqrt({n / w} * list_sum(list_transform(range(1, {w + 1}), lambda i: CASE WHEN ((f.mask >> ({w} - i)) & 1) = 1 THEN {gap(f'{two}[{cell2} + 1]', f'{two}[{cell2} + 2]')} ELSE {gap(f'{one}[{cell1} + 1]', f'{one}[{cell1} + 2]')} END)))"
    return f"""WITH {level2(name, w, th)},
placed AS (SELECT col.series_id, col.z, col.cell, coalesce(best.mask, 0) AS mask, coalesce(col.nb & best.mask, -1) AS leaf FROM col LEFT JOIN best ON best.cell = col.cell),
q AS (SELECT series_id, z, m, cell, nb FROM x WHERE series_id % 25 = 7 ORDER BY series_id LIMIT {limit}),
f AS (SELECT DISTINCT cell, mask, leaf FROM placed),
cellbound AS (SELECT q.series_id AS query_id, f.cell, min({wide}) AS b FROM q CROSS JOIN (SELECT DISTINCT cell FROM f) f GROUP BY ALL),
home AS (SELECT query_id, cell FROM (SELECT c.query_id, c.cell, row_number() OVER (PARTITION BY c.query_id ORDER BY (c.cell <> q.cell), c.b, c.cell) AS i FROM cellbound c JOIN q ON q.series_id = c.query_id) WHERE i = 1),
leafbound AS (SELECT q.series_id AS query_id, f.cell, f.leaf, {fine} AS b, NOT (q.cell = f.cell AND (f.leaf = -1 OR q.nb & f.mask = f.leaf)) AS foreign_leaf FROM q JOIN home h ON h.query_id = q.series_id JOIN f ON f.cell = h.cell),
chosen AS (SELECT query_id, cell, leaf FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY foreign_leaf, b, leaf) AS i FROM leafbound) WHERE i = 1),
d AS (SELECT o.query_id, p.series_id, list_distance(q.z, p.z) AS distance FROM chosen o JOIN q ON q.series_id = o.query_id JOIN placed p ON p.cell = o.cell AND p.leaf = o.leaf),
r AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY distance, series_id) AS rank FROM d)
SELECT query_id, CAST(rank AS INTEGER) AS rank, series_id, round(distance, 6) AS distance FROM r WHERE rank <= {k}"""


def cap() -> float:
    return CAP
