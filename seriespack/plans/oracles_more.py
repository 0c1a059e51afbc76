"""Results of the experiments and surfaces in DuckDB's SQL, recomputed from the given tables."""

from __future__ import annotations

from . import oracles as O
from .experiments import LABEL_BITS, PRESETS, WIDE_SETS  # noqa: F401
from .queries import UNIVARIATE

_CENTS = "CAST(round(value * 100) AS BIGINT)"
_SECONDS = "epoch_us(ts) // 1000000"
_TYPES = ["click", "error", "purchase", "signup", "view"]


def _values(rows: list[tuple], names: str) -> str:
    return "(VALUES " + ", ".join("(" + ", ".join(f"'{x}'" if isinstance(x, str) else str(x) for x in r) + ")" for r in rows) + f") AS v({names})"


def _grid(seconds: int, users: int, types: list[str] | None) -> str:
    """(col, t, v): cents by group of users and type in buckets of time from the first to the last."""
    kinds = [(u * len(types or [""]) + k, u, t) for u in range(users) for k, t in enumerate(types or [""])]
    of = "e.u = k.u" + (" AND e.event_type = k.kind" if types else "")
    return f"""SELECT k.col, b.b - b.lo AS t, coalesce(sum(e.c), 0) AS v
  FROM (SELECT unnest(range(lo, hi + 1)) AS b, lo FROM (SELECT min({_SECONDS} // {seconds}) AS lo, max({_SECONDS} // {seconds}) AS hi FROM events)) b
  CROSS JOIN (SELECT * FROM {_values(kinds, 'col, u, kind')}) k
  LEFT JOIN (SELECT {_SECONDS} // {seconds} AS b, user_id % {users} AS u, event_type, {_CENTS} AS c FROM events) e ON e.b = b.b AND {of} GROUP BY ALL"""


def _smooth(source: str, size: int = 144) -> str:
    return f"SELECT col, t - {size - 1} AS t, v FROM (SELECT col, t, sum(v) OVER (PARTITION BY col ORDER BY t ROWS {size - 1} PRECEDING) AS v FROM ({source})) WHERE t >= {size - 1}"


def _run(source: str) -> str:
    return f"SELECT col, t, sum(v) OVER (PARTITION BY col ORDER BY t) AS v FROM ({source})"


_MEASURES = [(i, f, s, m) for i, (f, s, m) in enumerate((f, s, m) for f in "ANR" for s in "FO" for m in ("l_quantity", "l_extendedprice", "l_discount"))]
_DAILY18 = f"""SELECT k.col, d.t, coalesce(c.v, 0) AS v FROM (SELECT day, row_number() OVER (ORDER BY day) - 1 AS t FROM (SELECT DISTINCT CAST(l_shipdate AS DATE) AS day FROM lineitem)) d
  CROSS JOIN (SELECT * FROM {_values(_MEASURES, 'col, f, s, m')}) k
  LEFT JOIN (SELECT CAST(l_shipdate AS DATE) AS day, l_returnflag AS f, l_linestatus AS s, m, sum(CAST(round(x * 100) AS BIGINT)) AS v FROM (
    SELECT l_shipdate, l_returnflag, l_linestatus, unnest(['l_quantity', 'l_extendedprice', 'l_discount']) AS m, unnest([l_quantity, l_extendedprice, l_discount]) AS x FROM lineitem) GROUP BY ALL) c USING (day, f, s, m)"""
_STATE3 = f"""SELECT k.col, b.b - b.lo AS t, count(e.b) AS v FROM (SELECT unnest(range(lo, hi + 1)) AS b, lo FROM (SELECT min({_SECONDS} // 60) AS lo, max({_SECONDS} // 60) AS hi FROM events)) b
  CROSS JOIN (SELECT * FROM {_values(list(enumerate(['error', 'purchase', 'signup'])), 'col, kind')}) k
  LEFT JOIN (SELECT {_SECONDS} // 60 AS b, event_type FROM events) e ON e.b = b.b AND e.event_type = k.kind GROUP BY ALL"""
_STATE2 = """SELECT unnest([0, 1]) AS col, t, unnest([s, p]) AS v FROM (SELECT row_number() OVER (ORDER BY day) - 1 AS t, s, p FROM (
  SELECT CAST(o_orderdate AS DATE) AS day, max(ascii(o_orderstatus)) AS s, min(ascii(o_orderpriority)) AS p FROM orders GROUP BY ALL))"""
_WIDE64 = "SELECT i - 1 AS col, t, CAST(round(CAST(embedding[i] AS DOUBLE) * 1000000) AS BIGINT) AS v FROM (SELECT row_number() OVER (ORDER BY vec_id) - 1 AS t, embedding, unnest(range(1, 65)) AS i FROM embeddings)"
#: Values (col, t, v), number of columns, and whether each column is rescaled by its own bounds.
WIDE = {
    "wide80": (_smooth(_smooth(_grid(600, 16, _TYPES))), 80, True),
    "wide31": (_smooth(_smooth(_grid(600, 31, None))), 31, True),
    "wide18": (_run(_DAILY18), 18, True),
    "wide64": (_WIDE64, 64, False),
    "stair80": (_run(_grid(600, 16, _TYPES)), 80, False),
    "state3": (_STATE3, 3, False),
    "state2": (_STATE2, 2, True),
    "ev_pivot5": (_grid(3600, 1, _TYPES), 5, False),
    "li_quad": ("SELECT 0 AS col, row_number() OVER () - 1 AS t, 0 AS v FROM lineitem", 4, True),
}


def wide(name: str, w: int) -> str:
    """CTE ``q`` (col, t, x) of a wide dataset."""
    source, _, own = WIDE[name]
    bounds = "SELECT col, min(v) AS lo, max(v) AS hi FROM s GROUP BY col" if own else "SELECT col, lo, hi FROM (SELECT DISTINCT col FROM s), (SELECT min(v) AS lo, max(v) AS hi FROM s)"
    return f"s AS ({source}), q AS (SELECT col, t, CAST(((v - lo) * {(1 << w) - 1}) // greatest(hi - lo, 1) AS BIGINT) AS x FROM s JOIN ({bounds}) USING (col))"


def wide_bytes(name: str, w: int, preset: str) -> str:
    """(series_id, preset, width_bits, raw_bytes, body_bytes) of a wide dataset in segments."""
    dims, h = WIDE[name][1], w.bit_length() - 1
    pieces = f"c AS (SELECT col || '/' || (t // {O.SEGMENT}) AS series_id, t % {O.SEGMENT} AS t, x FROM q)"
    residuals = O.fixed(w, "0", "c") if preset == "speed" else f"{O.adaptive(w, source='c')}, r AS (SELECT series_id, t, residual FROM f WHERE t >= 0)"
    payload = "stored" if dims * w <= 32 else "(stored + 7) // 8 * 8"
    return f"""SELECT * FROM (WITH RECURSIVE {wide(name, w)}, {pieces}, {residuals}, {O.blocks(w, out='bc')},
  b AS (SELECT split_part(series_id, '/', 2) AS series_id, block_id, n, sum(stored) AS stored FROM bc GROUP BY ALL), {O.slots()},
  sums AS (SELECT series_id, count(*) AS slots, sum({payload}) AS payload, sum(CASE WHEN stored = 0 THEN (length(bin(n_blocks)) + 6) // 7 ELSE 0 END) AS runs FROM k GROUP BY ALL),
  lengths AS (SELECT series_id, sum(n) AS n FROM b GROUP BY ALL)
  SELECT '{name}' AS series_id, '{preset}' AS preset, CAST({w} AS BIGINT) AS width_bits, CAST(sum(n * {dims * w // 8}) AS BIGINT) AS raw_bytes,
    CAST(sum(coalesce((slots // 2) * {-(-2 * dims * h // 8)} + ((slots % 2) * {dims * h} + 7) // 8 + payload + runs, 0) + (n % 8) * {dims * w // 8}) AS BIGINT) AS body_bytes FROM lengths LEFT JOIN sums USING (series_id))"""


def _kept(counts: str) -> str:
    """What a lossless check says of (dataset_id, samples, dims): no mismatch, for each preset and width."""
    presets = ", ".join(f"'{p}'" for p in PRESETS)
    return f"""SELECT dataset_id, preset, CAST(w AS BIGINT) AS width_bits, samples, CAST(0 AS BIGINT) AS mismatches, CAST(samples * dims * w // 8 AS BIGINT) AS raw_bytes
  FROM ({counts}), (SELECT unnest([{presets}]) AS preset), (SELECT unnest([8, 16]) AS w)"""


_BYTES = """x AS (SELECT series_id, seg, row_number() OVER (PARTITION BY series_id, seg ORDER BY k, i) - 1 AS t, CAST('0x' || h AS BIGINT) AS x FROM (
  SELECT series_id, seg, k, unnest(regexp_extract_all(h, '..')) AS h, unnest(range(0, length(h) // 2)) AS i FROM (
    SELECT 'doc_bytes_' || lang AS series_id, doc_id AS k, doc_id // 64 AS seg, hex(encode(text)) AS h FROM documents WHERE length(text) > 0
    UNION ALL SELECT 'page_bytes', page_id, page_id // 64, hex(encode(html)) FROM pages WHERE length(html) > 0)))"""

_POINTS = "SELECT vec_id, CAST(label AS BIGINT) AS label, i - 1 AS i, CAST(round(CAST(embedding[i] AS DOUBLE) * 1000000) AS BIGINT) AS v FROM (SELECT vec_id, label, embedding, unnest(range(1, 65)) AS i FROM embeddings)"


def _accuracy(bits: int) -> str:
    points = _POINTS if not bits else f"SELECT vec_id, label, i, CAST(((v - lo) * {(1 << bits) - 1}) // greatest(hi - lo, 1) * 1000 AS BIGINT) AS v FROM ({_POINTS}), (SELECT min(v) AS lo, max(v) AS hi FROM ({_POINTS}))"
    return f"""SELECT * FROM (WITH p AS ({points}), c AS (SELECT label AS guess, i, CAST(sum(v) AS BIGINT) // count(*) AS c FROM p GROUP BY ALL),
  d AS (SELECT vec_id, label, guess, sum((v - c) * (v - c)) AS d FROM p JOIN c USING (i) GROUP BY ALL)
  SELECT count(*) AS vectors, count(*) FILTER (label = guess) AS "right", CAST({bits} AS BIGINT) AS bits FROM (SELECT * FROM d QUALIFY row_number() OVER (PARTITION BY vec_id ORDER BY d, guess) = 1))"""


def _presteps(w: int) -> str:
    pack = O._BP.replace("series_id AS dataset_id", "series_id")
    size = "SELECT series_id, '{}' AS pre_step, CAST({} AS BIGINT) AS width_bits, CAST(sum(CASE WHEN n = 128 THEN 1 + 16 * bits ELSE tail END) AS BIGINT) AS enc_bytes FROM ({}) GROUP BY series_id"
    zigged = f"WITH {O.prep(O.RANKED, w)}, {O.fixed(w, '0')}, y AS (SELECT series_id, t, {O.zig('residual')} AS x FROM r) "
    return f"SELECT * FROM (WITH {O.prep(O.RANKED, w)} {size.format('none', w, pack)}) UNION ALL SELECT * FROM ({zigged} {size.format('lag1_zigzag', w, pack.replace('FROM q', 'FROM y'))})"


def _two() -> str:
    return f"""WITH {O.raw(['ev_value', 'ev_walk', 'ord_total'])}, o AS (SELECT series_id, v AS o FROM s WHERE t = 0),
  l AS (SELECT series_id, CAST(v - o AS HUGEINT) AS y, CAST(lag(v, 1) {O._BY} - o AS HUGEINT) AS p, CAST(lag(v, 2) {O._BY} - o AS HUGEINT) AS z FROM s JOIN o USING (series_id)),
  m AS (SELECT series_id, count(*) AS n, CAST(sum(p * p) AS DOUBLE) AS pp, CAST(sum(z * z) AS DOUBLE) AS qq, CAST(sum(p * z) AS DOUBLE) AS pq, CAST(sum(y * p) AS DOUBLE) AS yp, CAST(sum(y * z) AS DOUBLE) AS yq FROM l WHERE z IS NOT NULL GROUP BY series_id)
  SELECT series_id, n, round((yp * qq - yq * pq) / (pp * qq - pq * pq), 4) AS a, round((yq * pp - yp * pq) / (pp * qq - pq * pq), 4) AS b FROM m"""


_EVENTS = f"SELECT event_type, user_id, ts, event_id, {_CENTS} AS c FROM events"
_SESSIONS = f"""WITH e AS ({_EVENTS}), m AS (SELECT *, CASE WHEN ts - lag(ts) OVER w <= INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM e WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
  g AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS g FROM m)
  SELECT epoch_us(min(ts)) AS start, epoch_us(max(ts) + INTERVAL 30 MINUTE) AS "end", CAST(user_id AS VARCHAR) AS series_id, CAST(sum(c) AS BIGINT) AS total, count(*) AS n
  FROM g GROUP BY user_id, g HAVING max(ts) + INTERVAL 30 MINUTE <= (SELECT max(ts) - INTERVAL 1 HOUR FROM events)"""
_SET = "SELECT user_id FROM events WHERE event_type = '{}'"

ORACLES = {
    "q60_stream_late_rows": f"""WITH e AS ({_EVENTS}), n AS (SELECT event_type, max(ts) AS newest FROM e WHERE event_id % 10 <> 0 GROUP BY event_type)
  SELECT event_type AS series_id, count(*) AS n, CAST(sum(c) AS BIGINT) AS total FROM e JOIN n USING (event_type) WHERE event_id % 10 = 0 AND ts < newest GROUP BY event_type""",
    "q60_stream_idle_flush": O.ORACLES["q58_stream_encode_equals_batch"],
    "q60_stream_sessions": _SESSIONS,
    "q73_lossless_univariate": f"WITH {O.raw(O.CORPUS)} " + _kept("SELECT series_id AS dataset_id, count(*) AS samples, 1 AS dims FROM s GROUP BY series_id"),
    "q73_lossless_wide": _kept(" UNION ALL ".join(f"SELECT '{n}' AS dataset_id, count(*) AS samples, {dims} AS dims FROM ({source}) WHERE col = 0" for n, (source, dims, _) in WIDE.items())),
    "q74_wide_sizes": " UNION ALL ".join(wide_bytes(n, w, p) for w in (8, 16) for n in ("wide18", "state3", "state2", "wide80", "stair80") for p in ("speed", "balanced")),
    "q75_byte_series_speed": f"""WITH {_BYTES}, c AS (SELECT series_id || '/' || seg AS series_id, t, x FROM x), {O.fixed(8, '0', 'c')}, {O.blocks(8)}, {O.slots()}, {O.bodies(8)}
  SELECT {O._WHOLE} AS series_id, CAST(sum(n) AS BIGINT) AS raw_bytes, CAST(sum({O._BODY}) AS BIGINT) AS enc_bytes FROM z GROUP BY ALL""",
    "q76_gain_by_stratum": f"""WITH {O._RATIOS}, {O._paired('balanced', 'lag1')} SELECT CASE WHEN b >= 4 THEN '4 or more' ELSE 'below 4' END AS stratum, width_bits, count(*) AS n, count(*) FILTER (a > b) AS wins, round(avg(a / b), 6) AS mean_gain FROM pairs GROUP BY ALL""",
    "q77_nmse_corpus": " UNION ALL ".join(
        f"SELECT name AS series_id, CAST({w} AS BIGINT) AS width_bits, nmse, nmse < 0.01 AS below_one_percent FROM (WITH {O.raw(O.CORPUS)}, d AS (SELECT series_id AS name, CAST(v AS DOUBLE) AS v FROM s) {O._nmse(w, 'SELECT * FROM d')})" for w in (8, 16)
    ),
    "q78_label_accuracy": " UNION ALL ".join(_accuracy(b) for b in (0, *LABEL_BITS)),
    "q79_layouts_by_columns": f"""WITH {wide('wide64', 8)}, c AS (SELECT CAST(col AS VARCHAR) AS series_id, t, x FROM q), {O.fixed(8, '0', 'c')}, {O.blocks(8)},
  p AS (SELECT dims, block_id, sum(stored) AS w FROM b, (SELECT unnest([1, 2, 4, 5, 8, 16, 31, 32, 64]) AS dims) WHERE n = 8 AND CAST(series_id AS INTEGER) < dims GROUP BY ALL)
  SELECT CAST(dims AS BIGINT) AS dims, CAST(sum(w) AS BIGINT) AS column_bytes, CAST(sum((w + 7) // 8 * 8) AS BIGINT) AS row_bytes FROM p GROUP BY dims""",
    "q80_prestep_sizes": " UNION ALL ".join(_presteps(w) for w in (8, 16)),
    "q81_two_coefficients": _two(),
    "q82_exact_scaling": f"SELECT name, count(*) AS n, CAST(sum(CAST(round(v * 100) AS BIGINT)) AS BIGINT) AS total, count(*) FILTER (CAST(round(v * 100) AS BIGINT) / 100 <> v) AS changed FROM ({O.FLOATS}) GROUP BY name",
    "q85_top_blocks": f"""WITH {O.prep(UNIVARIATE, 16)}, {O.fixed(16, '0')}, g AS (SELECT series_id, t // 8 AS block_id, CAST({O.bits(f"bit_or({O.zig('residual')})")} AS BIGINT) AS bits, CAST(sum(abs(residual)) AS BIGINT) AS total FROM r GROUP BY ALL)
  SELECT series_id, row_number() OVER (PARTITION BY series_id ORDER BY bits DESC, total DESC, block_id) AS place, block_id, bits, total FROM g QUALIFY place <= 5""",
    "q86_json_channel": """SELECT event_type AS series_id, row_number() OVER w - 1 AS t, coalesce(last_value(CAST(json_extract(props, '$.k') AS BIGINT) IGNORE NULLS) OVER (PARTITION BY event_type ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING), 0) AS v
  FROM events WINDOW w AS (PARTITION BY event_type ORDER BY ts, event_id)""",
    "q87_functions_of_ones_own": f"""WITH {O.prep(['ev_walk'], 16)}, {O.fixed(16, '0')}, z AS (SELECT t // 64 AS block_id, {O.zig('residual')} AS z FROM r)
  SELECT block_id, CAST({O.bits('bit_or(z)')} AS BIGINT) AS own_bits, CAST({O.bits('bit_or(z)')} AS BIGINT) AS bits, CAST(sum(z) AS BIGINT) AS total FROM z GROUP BY block_id""",
    "q88_set_operations": f"""SELECT 'both' AS kind, user_id FROM ({_SET.format('purchase')} INTERSECT {_SET.format('error')}) UNION ALL
  SELECT 'first only', user_id FROM ({_SET.format('purchase')} EXCEPT {_SET.format('error')}) UNION ALL SELECT 'either', user_id FROM ({_SET.format('purchase')} UNION {_SET.format('error')})""",
    "q89_sampled_advice": O.ORACLES["q54_advisor"].replace(O.quant(16), f"{O.quant(16, out='q0')}, q AS (SELECT series_id, t // 512 // 8 * 512 + t % 512 AS t, x FROM q0 WHERE t // 512 % 8 = 0)"),
    "q90_text_and_binary_sources": f"WITH {O.prep(['ev_walk', 'ev_total'], 16)} SELECT series_id, t, x AS from_text, x AS from_dump FROM q",
    "q91_datasource_write": f"WITH {O.prep(['ev_ma64'], 16)} SELECT t, x, x AS streamed FROM q",
}
