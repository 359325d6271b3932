"""The registered queries' SQL twins, for DuckDB on the same tables.

Everything is put together from a few named relations: ``long`` (a fixture's
samples), ``q`` and ``db`` (held-out queries and candidates), ``bounds`` (all
lower bounds by windows and sums) and ``warp`` (the distance, by a recursion
over anti-diagonals that carries two lists).
"""

from __future__ import annotations

def _grid(source: str, steps: int) -> str:
    """Sparse sums ``raw`` onto the whole grid."""
    return f"""raw AS ({source}),
long AS (SELECT k.series_id, g.pos, coalesce(r.val, 0)::BIGINT AS val
  FROM (SELECT DISTINCT series_id FROM raw) k CROSS JOIN (SELECT unnest(range(1, {steps + 1}))::INT AS pos) g
  LEFT JOIN raw r ON r.series_id = k.series_id AND r.pos = g.pos)"""


def _supplier(pos: str, steps: int) -> str:
    return _grid(
        f"SELECT l_suppkey AS series_id, ({pos})::INT AS pos, sum(l_quantity)::BIGINT AS val FROM lineitem WHERE ({pos}) BETWEEN 1 AND {steps} GROUP BY 1, 2",
        steps,
    )


def _first(select: str, n: int) -> str:
    """The first n values of each key, of keys with as many; ``select`` gives series_id, val, pos."""
    return f"""every AS ({select}),
long AS (SELECT series_id, pos::INT AS pos, val::BIGINT AS val FROM every
  WHERE pos <= {n} AND series_id IN (SELECT series_id FROM every GROUP BY 1 HAVING count(*) >= {n}))"""


def _lists(select: str, n: int) -> str:
    """The first n entries of a list, of lists with as many; ``select`` gives series_id, l."""
    return f"""every AS ({select}),
long AS (SELECT series_id, p::INT AS pos, l[p]::BIGINT AS val FROM every CROSS JOIN (SELECT unnest(range(1, {n + 1})) AS p) WHERE len(l) >= {n})"""


def _walked(base: str, n: int) -> str:
    return f"""{base.replace('long AS (', 'flat AS (')},
long AS (SELECT series_id, pos, (sum({n} * val - s) OVER (PARTITION BY series_id ORDER BY pos))::BIGINT AS val
  FROM (SELECT *, sum(val) OVER (PARTITION BY series_id) AS s FROM flat))"""


_DAY = "date_diff('day', DATE '1995-01-02', l_shipdate::DATE)"
_MONTH = "(year({0}) - 1995) * 12 + month({0})"
_PART = "SELECT l_partkey AS series_id, l_quantity AS val, row_number() OVER (PARTITION BY l_partkey ORDER BY l_shipdate, l_orderkey, l_linenumber) AS pos FROM lineitem"
_USER = "SELECT user_id AS series_id, floor(value * 100 + 0.5) AS val, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS pos FROM events"
_NATION = f"""SELECT c_nationkey::BIGINT AS series_id, ({_MONTH.format('o_orderdate')})::INT AS pos, sum(floor(o_totalprice * 100 + 0.5))::BIGINT AS val
  FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey
  WHERE ({_MONTH.format('o_orderdate')}) BETWEEN 1 AND 80 GROUP BY 1, 2"""
_WORDS = "SELECT doc_id AS series_id, list_transform(string_split(text, ' '), lambda s: length(s)) AS l FROM documents"
_CHARS = "SELECT doc_id AS series_id, list_transform(range(1, 1025), lambda i: unicode(substring(text, i, 1))) AS l FROM documents WHERE length(text) >= 1024"
_TAGS = "SELECT page_id AS series_id, list_transform(string_split(html, '<'), lambda s: length(s)) AS l FROM pages"
_VECTORS = "SELECT vec_id AS series_id, list_transform(embedding, lambda e: floor(e::DOUBLE * 1e6 + 0.5)) AS l FROM embeddings"

#: Fixture to the relations that end in ``long``.
FIXTURES = {
    "supplier_month_raw": _supplier(_MONTH.format("l_shipdate"), 83),
    "supplier_month_walk": _walked(_supplier(_MONTH.format("l_shipdate"), 83), 83),
    "supplier_week_raw": _supplier(f"{_DAY} // 7 + 1", 256),
    "supplier_week_walk": _walked(_supplier(f"{_DAY} // 7 + 1", 256), 256),
    "supplier_day_walk": _walked(_supplier(f"{_DAY} + 1", 1000), 1000),
    "part_qty_raw": _first(_PART, 24),
    "part_qty_walk": _walked(_first(_PART, 24), 24),
    "user_raw": _first(_USER, 48),
    "user_walk": _walked(_first(_USER, 48), 48),
    "embedding_walk": _walked(_lists(_VECTORS, 64), 64),
    "word_length_raw": _lists(_WORDS, 251),
    "word_walk": _walked(_lists(_WORDS, 251), 251),
    "char_walk": _walked(_lists(_CHARS, 1024), 1024),
    "nation_month": _grid(_NATION, 80),
    "tag_walk": _walked(_lists(_TAGS, 64), 64),
}


def series(name: str) -> str:
    return f"WITH {FIXTURES[name]} SELECT series_id, pos, val FROM long"


def split(name: str, n_queries: int) -> str:
    """Adds ``packed``, ``q(query_id, y)`` and ``db(series_id, v)``."""
    return f"""{FIXTURES[name]},
packed AS (SELECT series_id, list(val::DOUBLE ORDER BY pos) AS v FROM long GROUP BY series_id),
placed AS (SELECT *, row_number() OVER (ORDER BY (z * z + 1) % 1000003, series_id) AS place FROM (SELECT series_id, v, (series_id * 7919 + 1299709) % 1000003 AS z FROM packed)),
held AS (SELECT least({n_queries}, count(*) // 2) AS n FROM packed),
q AS (SELECT series_id AS query_id, v AS y FROM placed WHERE place <= (SELECT n FROM held)),
db AS (SELECT series_id, v FROM placed WHERE place > (SELECT n FROM held))"""


def cost(x: str, p: str) -> str:
    return {"1": f"abs({x})", "2": f"({x}) * ({x})", "inf": f"abs({x})"}[p]


def total(x: str, p: str) -> str:
    return f"max({x})" if p == "inf" else f"sum({x})"


def warp(n: int, w: int, p: str = "1", pairs: str = "SELECT query_id, series_id, v AS x, y FROM db CROSS JOIN q", name: str = "warp") -> str:
    """``pairs`` and ``warp(query_id, series_id, dtw)`` for series of n samples.

    A step holds the cells of one anti-diagonal that the band leaves, and those
    of the one before; only the last step of a pair is kept.
    """
    first = lambda k: f"greatest(0, {k} - {n - 1}, ceil(({k} - {w}) / 2.0)::INT)"
    last = lambda k: f"least({n - 1}, {k}, floor(({k} + {w}) / 2.0)::INT)"
    c = cost("x[i + 1] - y[k + 1 - i + 1]", p)
    best = f"least(a[i - {first('k')}], a[i - {first('k')} + 1], b[i - {first('(k - 1)')}])"
    value = f"greatest({c}, {best})" if p == "inf" else f"{c} + {best}"
    return f"""{name}_pairs AS ({pairs}),
{name}_steps(query_id, series_id, k, a, b) USING KEY (query_id, series_id) AS (
  SELECT query_id, series_id, 0, [{cost("x[1] - y[1]", p)}], []::DOUBLE[] FROM {name}_pairs
  UNION
  SELECT s.query_id, s.series_id, k + 1, list_transform(range({first('(k + 1)')}, {last('(k + 1)')} + 1), lambda i: {value}), a
  FROM {name}_steps s JOIN {name}_pairs t ON s.query_id = t.query_id AND s.series_id = t.series_id WHERE k < {2 * n - 2}),
{name} AS (SELECT query_id, series_id, a[1] AS dtw FROM {name}_steps)"""


def bounds(n: int, w: int, p: str = "1", d: int = 8) -> str:
    """``pos_pairs`` (samples of all pairs with envelopes) and ``bounds(query_id, series_id, box, pass1, gap2, pass2, lp)``."""
    add = "greatest(pass1, gap2)" if p == "inf" else "pass1 + gap2"
    frame = f"ORDER BY pos ROWS BETWEEN {w} PRECEDING AND {w} FOLLOWING"
    step = n // d
    block = f"least((pos - 1) // {step}, {d - 1})"
    size = f"(CASE WHEN {block} = {d - 1} THEN {n - step * (d - 1)} ELSE {step} END)"
    box_cost = {"1": "g", "2": "g * g / size", "inf": "g / size"}[p]
    return f"""q_long AS (SELECT query_id, pos, y[pos] AS y FROM q CROSS JOIN (SELECT unnest(range(1, {n + 1})) AS pos)),
q_env AS (SELECT *, min(y) OVER (PARTITION BY query_id {frame}) AS lo, max(y) OVER (PARTITION BY query_id {frame}) AS hi FROM q_long),
db_long AS (SELECT series_id, pos, v[pos] AS x FROM db CROSS JOIN (SELECT unnest(range(1, {n + 1})) AS pos)),
clamped AS (SELECT query_id, series_id, e.pos, x, y, lo, hi, least(greatest(x, lo), hi) AS h FROM db_long b JOIN q_env e ON b.pos = e.pos),
pos_pairs AS (SELECT *, min(h) OVER (PARTITION BY query_id, series_id {frame}) AS lo2, max(h) OVER (PARTITION BY query_id, series_id {frame}) AS hi2 FROM clamped),
flat_bounds AS (SELECT query_id, series_id, {total(cost('x - h', p), p)} AS pass1, {total(cost('greatest(lo2 - y, y - hi2, 0)', p), p)} AS gap2, {total(cost('x - y', p), p)} AS lp
  FROM pos_pairs GROUP BY 1, 2),
box_parts AS (SELECT query_id, series_id, {block} AS k, greatest(sum(lo) - sum(x), sum(x) - sum(hi), 0) AS g, max({size}) AS size FROM pos_pairs GROUP BY 1, 2, 3),
boxes AS (SELECT query_id, series_id, {total(box_cost, p)} AS box FROM box_parts GROUP BY 1, 2),
bounds AS (SELECT query_id, series_id, box, pass1, gap2, {add} AS pass2, lp FROM flat_bounds JOIN boxes USING (query_id, series_id))"""


def measured(name: str, n_queries: int, n: int, w: int, p: str = "1", d: int = 8) -> str:
    """Relations up to ``m``: all bounds and the distance of all pairs."""
    return f"""{split(name, n_queries)},
{bounds(n, w, p, d)},
{warp(n, w, p)},
m AS (SELECT * FROM bounds JOIN warp USING (query_id, series_id))"""


def counted_only(name: str, n_queries: int, n: int, w: int, d: int = 8, source: str = "bounds", keys: str = "query_id", more: str = "") -> str:
    """Relations up to ``m`` for counts alone, with the distances that can change a count.

    A pair can't if an earlier candidate's unwarped distance, which no warping
    distance exceeds, is no more than the pair's bound; it is infinite in ``m``.
    """
    before = f"PARTITION BY {keys} ORDER BY {{}} ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING"
    beaten = " AND ".join(f"pass2 >= coalesce(min(lp) OVER ({before.format(order)}), 'inf'::DOUBLE)" for order in ("series_id", "box, series_id"))
    wanted = f"SELECT DISTINCT query_id, series_id FROM (SELECT *, {beaten} AS beaten FROM {source}) WHERE NOT beaten"
    return f"""{split(name, n_queries)},
{bounds(n, w, '1', d)}{more},
wanted AS ({wanted}),
{warp(n, w, '1', 'SELECT query_id, series_id, v AS x, y FROM wanted JOIN db USING (series_id) JOIN q USING (query_id)')},
m AS (SELECT b.*, coalesce(dtw, 'inf'::DOUBLE) AS dtw FROM {source} b LEFT JOIN warp USING (query_id, series_id))"""


def pages(n: int, w: int, page_rows: int, d: int = 8) -> str:
    """``points``, their pages, and ``page_hits(query_id, page_id, rows, page_bound)`` for p = 1, after ``split`` and ``bounds``."""
    step = n // d
    block = f"least((pos - 1) // {step}, {d - 1}) + 1"
    sums = ", ".join(f"sum(x) FILTER (WHERE {block} = {k}) AS s{k}" for k in range(1, d + 1))
    sides = ", ".join(f"sum(lo) FILTER (WHERE {block} = {k}) AS lo{k}, sum(hi) FILTER (WHERE {block} = {k}) AS hi{k}" for k in range(1, d + 1))
    least = ", ".join(f"min(s{k}) AS a{k}, max(s{k}) AS b{k}" for k in range(1, d + 1))
    gaps = " + ".join(f"greatest(lo{k} - b{k}, a{k} - hi{k}, 0)" for k in range(1, d + 1))
    return f"""points AS (SELECT series_id, {sums} FROM db_long GROUP BY 1),
tiles AS (SELECT greatest(1, ceil(sqrt(p)))::INT AS strips, ceil(p / greatest(1, ceil(sqrt(p))))::INT AS per FROM (SELECT greatest(1, ceil(count(*) / {page_rows})) AS p FROM points)),
ranked1 AS (SELECT s1, row_number() OVER (ORDER BY s1) AS r, count(*) OVER () AS c FROM points),
edges1 AS (SELECT s1 AS e FROM ranked1 CROSS JOIN tiles CROSS JOIN (SELECT unnest(range(1, 1000)) AS k) WHERE k < strips AND r = ceil(k / strips * c)),
striped AS (SELECT p.*, (SELECT count(*) FROM edges1 WHERE e < p.s1) AS strip FROM points p),
ranked2 AS (SELECT strip, s2, row_number() OVER (PARTITION BY strip ORDER BY s2) AS r, count(*) OVER (PARTITION BY strip) AS c FROM striped),
edges2 AS (SELECT strip, s2 AS e FROM ranked2 CROSS JOIN tiles CROSS JOIN (SELECT unnest(range(1, 1000)) AS k) WHERE k < per AND r = ceil(k / per * c)),
placed_points AS (SELECT p.*, strip * (SELECT per FROM tiles) + (SELECT count(*) FROM edges2 e WHERE e.strip = p.strip AND e.e < p.s2) AS page_id FROM striped p),
page_table AS (SELECT page_id, count(*) AS rows, {least} FROM placed_points GROUP BY 1),
query_sides AS (SELECT query_id, {sides} FROM q_env GROUP BY 1),
page_hits AS (SELECT query_id, page_id, rows, {gaps} AS page_bound FROM page_table CROSS JOIN query_sides)"""


def counted(method: str, tests: tuple[str, ...], order: str, source: str = "m", keys: str = "query_id") -> str:
    """One method's sequential counts by query, from ``m``."""
    done = {"box": "TRUE", "pass1": "TRUE", "pass2": "TRUE"}
    so_far = "TRUE"
    for name in done:
        if name in tests:
            so_far = f"{so_far} AND {name} < b"
        done[name] = so_far
    sums = ", ".join(f"count(*) FILTER (WHERE {test}) AS after_{name}" for name, test in done.items())
    return f"""SELECT {keys}, '{method}' AS method, count(*) AS candidates, {sums}, count(*) FILTER (WHERE {done['pass2']}) AS dtw_done
  FROM (SELECT *, coalesce(min(dtw) OVER (PARTITION BY {keys} ORDER BY {order} ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 'inf'::DOUBLE) AS b FROM {source}) GROUP BY {keys}"""


SEQUENTIAL = {
    "scan_pass1": (("pass1",), "series_id"), "scan_pass2": (("pass1", "pass2"), "series_id"),
    "box_only": (("box",), "box, series_id"), "box_pass1": (("box", "pass1"), "box, series_id"), "box_pass2": (("box", "pass1", "pass2"), "box, series_id"),
}


def counts(methods: list[str], source: str = "m", keys: str = "query_id") -> str:
    return " UNION ALL ".join(counted(m, *SEQUENTIAL[m], source, keys) for m in methods)
