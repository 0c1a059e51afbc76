"""The catalogue's results in DuckDB's SQL, recomputed from the given tables."""

from __future__ import annotations

from ..sources.builders import LINE_ORDER

UNIVARIATE = ["ev_value", "ev_total", "ev_walk", "ev_ma64", "ev_ma64x2", "ev_walk2", "ev_ts", "li_day", "li_qty", "ord_total", "ord_cum"]
_EV = "(SELECT row_number() OVER (ORDER BY ts, event_id) - 1 AS t, CAST(round(value * 100) AS BIGINT) AS c, ts FROM events)"
_MA = f"(SELECT t - 63 AS t, CAST(s AS BIGINT) AS v FROM (SELECT t, sum(c) OVER (ORDER BY t ROWS 63 PRECEDING) AS s FROM {_EV}) WHERE t >= 63)"
_WALK = f"(SELECT t, CAST(sum(c - 5000) OVER (ORDER BY t) AS BIGINT) AS v FROM {_EV})"
_DAY = "CAST(l_shipdate AS DATE)"
SERIES = {
    "ev_value": f"SELECT t, c AS v FROM {_EV}",
    "ev_total": f"SELECT t, CAST(sum(c) OVER (ORDER BY t) AS BIGINT) AS v FROM {_EV}",
    "ev_walk": f"SELECT t, v FROM {_WALK}",
    "ev_ma64": f"SELECT t, v FROM {_MA}",
    "ev_ma64x2": f"SELECT t - 63 AS t, CAST(s AS BIGINT) AS v FROM (SELECT t, sum(v) OVER (ORDER BY t ROWS 63 PRECEDING) AS s FROM {_MA}) WHERE t >= 63",
    "ev_walk2": f"SELECT t, CAST(sum(v - m) OVER (ORDER BY t) AS BIGINT) AS v FROM {_WALK}, (SELECT CAST((sum(v) - (sum(v) % count(*) + count(*)) % count(*)) // count(*) AS BIGINT) AS m FROM {_WALK})",
    "ev_ts": f"SELECT t, epoch_us(ts) - (SELECT min(epoch_us(ts)) FROM events) AS v FROM {_EV}",
    "li_day": f"SELECT row_number() OVER (ORDER BY {_DAY}) - 1 AS t, CAST(date_diff('day', DATE '1970-01-01', {_DAY}) AS BIGINT) AS v FROM lineitem",
    "li_qty": f"SELECT row_number() OVER (ORDER BY {', '.join(LINE_ORDER)}) - 1 AS t, CAST(l_quantity AS BIGINT) AS v FROM lineitem",
    "ord_total": "SELECT t - 29 AS t, CAST(s AS BIGINT) AS v FROM (SELECT row_number() OVER (ORDER BY d) - 1 AS t, sum(c) OVER (ORDER BY d ROWS 29 PRECEDING) AS s FROM (SELECT CAST(o_orderdate AS DATE) AS d, sum(CAST(round(o_totalprice * 100) AS BIGINT)) AS c FROM orders GROUP BY d)) WHERE t >= 29",
    "ord_cum": "SELECT row_number() OVER (ORDER BY o_orderdate, o_orderkey) - 1 AS t, CAST(sum(CAST(round(o_totalprice * 100) AS BIGINT)) OVER (ORDER BY o_orderdate, o_orderkey) AS BIGINT) AS v FROM orders",
}
TYPED = "SELECT 'ev_val_' || event_type AS series_id, row_number() OVER (PARTITION BY event_type ORDER BY ts, event_id) - 1 AS t, CAST(round(value * 100) AS BIGINT) AS v FROM events"


_USERS = "SELECT user_id % 8 AS u, row_number() OVER (PARTITION BY user_id % 8 ORDER BY ts, event_id) - 1 AS t, CAST(round(value * 100) AS BIGINT) AS c FROM events"
_BY_TYPE = "SELECT event_type, row_number() OVER (PARTITION BY event_type ORDER BY ts, event_id) - 1 AS t, CAST(round(value * 100) AS BIGINT) AS c FROM events"
_KEYED = "SELECT row_number() OVER (ORDER BY {key}) - 1 AS t, CAST(round({value} * 100) AS BIGINT) AS v FROM {table}"
SERIES |= {
    "part_price": _KEYED.format(key="p_partkey", value="p_retailprice", table="part"),
    "cust_bal": _KEYED.format(key="c_custkey", value="c_acctbal", table="customer"),
    "supp_bal": _KEYED.format(key="s_suppkey", value="s_acctbal", table="supplier"),
}


def concatenated(points: str) -> str:
    """(series_id, t, v) of short series of 64 points (label, vec_id, p, v), with five interpolated points between."""
    return f"""WITH e AS ({points}), o AS (SELECT label, vec_id, (row_number() OVER (PARTITION BY label ORDER BY vec_id) - 1) * 69 AS off FROM (SELECT DISTINCT label, vec_id FROM e)),
  own AS (SELECT label, off + p AS t, v FROM e JOIN o USING (label, vec_id)),
  ends AS (SELECT label, off, max(CASE WHEN p = 63 THEN v END) AS last, max(CASE WHEN p = 0 THEN v END) AS first FROM e JOIN o USING (label, vec_id) GROUP BY ALL),
  gaps AS (SELECT a.label, a.off + 63 + i AS t, a.last + ((z.first - a.last) * i) // 6 AS v FROM ends a JOIN ends z ON z.label = a.label AND z.off = a.off + 69, (SELECT unnest(range(1, 6)) AS i))
  SELECT label, CAST(t AS BIGINT) AS t, CAST(v AS BIGINT) AS v FROM own UNION ALL SELECT label, CAST(t AS BIGINT), CAST(v AS BIGINT) FROM gaps"""


_EMB = "SELECT label, vec_id, i - 1 AS p, CAST(round(CAST(embedding[i] AS DOUBLE) * 1000000) AS BIGINT) AS v FROM (SELECT label, vec_id, embedding, unnest(range(1, 65)) AS i FROM embeddings)"
_EMB_WALK = f"SELECT label, vec_id, p, sum(v) OVER (PARTITION BY vec_id ORDER BY p) AS v FROM ({_EMB})"
#: Builders that make several series each.
GROUPED = {
    "ev_val_types": TYPED,
    "ev_run_types": f"SELECT 'ev_run_' || event_type AS series_id, t, CAST(sum(c) OVER (PARTITION BY event_type ORDER BY t) AS BIGINT) AS v FROM ({_BY_TYPE})",
    "ev_user_vals": f"SELECT 'ev_user_val_' || u AS series_id, t, c AS v FROM ({_USERS})",
    "ev_user_runs": f"SELECT 'ev_user_run_' || u AS series_id, t, CAST(sum(c) OVER (PARTITION BY u ORDER BY t) AS BIGINT) AS v FROM ({_USERS})",
    "emb_labels": f"SELECT 'emb_' || label AS series_id, t, v FROM ({concatenated(_EMB)})",
    "emb_walks": f"SELECT 'emb_walk_' || label AS series_id, t, v FROM ({concatenated(_EMB_WALK)})",
}
CORPUS = [*SERIES, *GROUPED]


def wrap(e: str, w: int) -> str:
    return f"(((({e}) + {1 << (w - 1)}) % {1 << w} + {1 << w}) % {1 << w} - {1 << (w - 1)})"


def zig(e: str) -> str:
    return f"(CASE WHEN {e} >= 0 THEN 2 * {e} ELSE -2 * {e} - 1 END)"


def bits(e: str) -> str:
    return f"(CASE WHEN {e} = 0 THEN 0 ELSE length(bin({e})) END)"


def raw(names: list[str]) -> str:
    parts = [GROUPED[n] if n in GROUPED else f"SELECT '{n}' AS series_id, t, v FROM ({SERIES[n]})" for n in names]
    return "s AS (" + " UNION ALL ".join(f"SELECT series_id, t, v FROM ({p})" for p in parts) + ")"


def quant(w: int, source: str = "s", out: str = "q") -> str:
    return f"{out} AS (SELECT series_id, t, CAST(((v - lo) * {(1 << w) - 1}) // greatest(hi - lo, 1) AS BIGINT) AS x FROM {source} JOIN (SELECT series_id, min(v) AS lo, max(v) AS hi FROM {source} GROUP BY series_id) USING (series_id))"


def prep(names: list[str], w: int) -> str:
    return f"{raw(names)}, {quant(w)}"


_BY = "OVER (PARTITION BY series_id ORDER BY t)"


def fixed(w: int, coef: str, source: str = "q", out: str = "r", more: str = "") -> str:
    one, two = f"coalesce(lag(x, 1) {_BY}, 0)", f"coalesce(lag(x, 2) {_BY}, 0)"
    inner = f"SELECT *, {wrap(f'x - {one}', w)} AS step, {wrap(f'{one} - {two}', w)} AS last FROM {source}"
    return f"{out} AS (SELECT series_id, t, {more} {wrap(f'step - ((last * {coef}) >> {w})', w)} AS residual FROM ({inner}))"


SEGMENT = 8192


def cut(source: str = "q", out: str = "c", length: int = SEGMENT) -> str:
    """CTE of series as segments that start anew, named by series and number."""
    return f"{out} AS (SELECT series_id || '/' || (t // {length}) AS series_id, t % {length} AS t, x FROM {source})"


_WHOLE = "split_part(series_id, '/', 1)"
_NUMBER = "CAST(split_part(series_id, '/', 2) AS BIGINT)"


def adaptive(w: int, update: str = "block", shift: int = 1, source: str = "q", stride: int = 2, clamp: bool = False, rounded: bool = False, case: bool = False, floor: bool = False) -> str:
    """CTE ``f``: t, residual, coef of every sample, by recursion over positions."""
    low, high = -(1 << (2 * w - 1)), (1 << (2 * w - 1)) - 1
    if clamp:
        low, high = -(1 << (w - 1)) << shift, (1 << w) << shift
    clip = lambda e: f"least(greatest({e}, {low}), {high})"
    last, n = f"i % {stride} = {stride - 1}", 8 // stride
    coef = f"gain >> {shift}" if update == "sample" else f"CASE WHEN i % 8 = 0 THEN gain >> {shift} ELSE coef END"
    total = f"(CASE WHEN i % 8 = 0 THEN 0 ELSE total END) + (CASE WHEN {last} THEN push ELSE 0 END)"
    mean = f"(total2 >> {n.bit_length() - 1})" if floor else f"(total2 // {n})"
    gain = f"CASE WHEN {last} THEN {clip('gain + push')} ELSE gain END" if update == "sample" else f"CASE WHEN i % 8 = 7 THEN {clip(f'gain + {mean}')} ELSE gain END"
    sign = "(CASE WHEN residual > 0 THEN 1 ELSE -1 END)" if case else "sign(residual)"
    product = f"coef2 * step + {1 << (w - 1)}" if rounded else "coef2 * step"
    return f"""f(series_id, t, prev, step, gain, coef, total, residual) AS (
  SELECT DISTINCT series_id, CAST(-1 AS BIGINT), CAST(0 AS BIGINT), CAST(0 AS BIGINT), CAST(0 AS BIGINT), CAST(0 AS BIGINT), CAST(0 AS BIGINT), CAST(0 AS BIGINT) FROM {source}
  UNION ALL
  SELECT series_id, i, x, now, CAST({gain} AS BIGINT), coef2, CAST(total2 AS BIGINT), residual FROM (
    SELECT *, {total} AS total2 FROM (SELECT *, {sign} * step AS push FROM (
      SELECT *, {wrap(f'now - (({product}) >> {w})', w)} AS residual FROM (
        SELECT f.series_id, z.t AS i, z.x, f.step, f.gain, f.total, f.coef, {wrap('z.x - f.prev', w)} AS now, {coef.replace('i %', 'z.t %')} AS coef2
        FROM f JOIN {source} z ON z.series_id = f.series_id AND z.t = f.t + 1)))))"""


def learnt_sizes(names: list[str], w: int, segmented: bool = False, **options) -> str:
    """(series_id, n, enc_bytes) of the learning forecaster, of whole series or of segments."""
    source = "c" if segmented else "q"
    cutting = f"{cut()}, " if segmented else ""
    name = _WHOLE if segmented else "series_id"
    return f"""WITH RECURSIVE {prep(names, w)}, {cutting}{adaptive(w, source=source, **options)}, r AS (SELECT series_id, t, residual FROM f WHERE t >= 0), {blocks(w)}, {slots()}, {bodies(w)}
  SELECT {name} AS series_id, CAST(sum(n) AS BIGINT) AS n, CAST(sum({_BODY}) AS BIGINT) AS enc_bytes FROM z GROUP BY ALL"""


def blocks(w: int, source: str = "r", keys: str = "series_id", block: int = 8, out: str = "b") -> str:
    return f"""{out} AS (SELECT *, CASE WHEN bits >= {w - 1} THEN {w} ELSE bits END AS stored FROM (
  SELECT {keys}, block_id, n, {bits('o')} AS bits FROM (SELECT {keys}, t // {block} AS block_id, count(*) AS n, bit_or({zig('residual')}) AS o FROM {source} GROUP BY ALL)))"""


def slots(keys: str = "series_id", block: int = 8, out: str = "k") -> str:
    order = f"OVER (PARTITION BY {keys} ORDER BY block_id)"
    return f"""{out} AS (SELECT {keys}, slot, min(block_id) AS first_block, count(*) AS n_blocks, max(stored) AS stored FROM (
  SELECT *, sum(first) {order} - 1 AS slot FROM (SELECT *, CASE WHEN stored > 0 OR coalesce(lag(stored) {order}, 1) > 0 THEN 1 ELSE 0 END AS first FROM b WHERE n = {block})) GROUP BY ALL)"""


def bodies(w: int, keys: str = "series_id", group: int = 2, block: int = 8, out: str = "z") -> str:
    """CTE of exact body sizes of univariate lag-1-like residuals in ``b`` and ``k``."""
    h = w.bit_length() - 1
    return f"""{out} AS (SELECT {keys}, CAST(n AS BIGINT) AS n, CAST(coalesce(slots, 0) AS BIGINT) AS slots, CAST(coalesce(payload, 0) AS BIGINT) AS payload_bytes, CAST(coalesce(runs, 0) AS BIGINT) AS run_bytes,
  CAST(tail AS BIGINT) AS tail_bytes, CAST(coalesce((slots // {group}) * {-(-group * h // 8)} + ((slots % {group}) * {h} + 7) // 8, 0) AS BIGINT) AS header_bytes, CAST(coalesce(zero_blocks, 0) AS BIGINT) AS zero_blocks
  FROM (SELECT {keys}, sum(n) AS n, sum(CASE WHEN n < {block} THEN n ELSE 0 END) * {w // 8} AS tail FROM b GROUP BY {keys})
  LEFT JOIN (SELECT {keys}, count(*) AS slots, sum((stored * {block} + 7) // 8) AS payload, sum(CASE WHEN stored = 0 THEN (length(bin(n_blocks)) + 6) // 7 ELSE 0 END) AS runs, sum(CASE WHEN stored = 0 THEN n_blocks ELSE 0 END) AS zero_blocks FROM k GROUP BY {keys}) USING ({keys}))"""


_BODY = "header_bytes + payload_bytes + run_bytes + tail_bytes"


def lag1_sizes(names: list[str], w: int) -> str:
    return f"{prep(names, w)}, {fixed(w, '0')}, {blocks(w)}, {slots()}, {bodies(w)}"


def cut_lag1(names: list[str], w: int, group: int = 2) -> str:
    return f"{prep(names, w)}, {cut()}, {fixed(w, '0', 'c')}, {blocks(w)}, {slots()}, {bodies(w, group=group)}"


def _both_widths(body: str, tail: str) -> str:
    """A result for 8 and 16 bits, ``W`` standing for the width in ``tail``."""
    return " UNION ALL ".join(f"SELECT * FROM (WITH {body.replace('WIDTH', str(w)) if isinstance(body, str) else body(w)} {tail.replace('WIDTH', str(w))})" for w in (8, 16))


def method_sizes(names: list[str]) -> str:
    """Sizes (dataset_id, method, width_bits, raw_bytes, enc_bytes) of the methods that SQL can size."""
    parts = []
    for w in (8, 16):
        for method, coef in (("lag1", "0"), ("double_delta", str(1 << w)), ("two_point_mean", str(-(1 << (w - 1))))):
            parts.append(f"SELECT * FROM (WITH {prep(names, w)}, {fixed(w, coef)}, {blocks(w)}, {slots()}, {bodies(w)} SELECT series_id AS dataset_id, '{method}' AS method, CAST({w} AS BIGINT) AS width_bits, n * {w // 8} AS raw_bytes, {_BODY} AS enc_bytes FROM z)")
        parts.append(f"SELECT series_id AS dataset_id, 'balanced' AS method, CAST({w} AS BIGINT) AS width_bits, n * {w // 8} AS raw_bytes, enc_bytes FROM ({learnt_sizes(names, w)})")
        parts.append(f"SELECT * FROM (WITH {prep(names, w)} SELECT dataset_id, 'bp128' AS method, CAST({w} AS BIGINT) AS width_bits, CAST(sum(n) * {w // 8} AS BIGINT) AS raw_bytes, CAST(sum(CASE WHEN n = 128 THEN 1 + 16 * bits ELSE tail END) AS BIGINT) AS enc_bytes FROM ({_BP}) GROUP BY dataset_id)")
        parts.append(f"SELECT series_id AS dataset_id, 'raw' AS method, CAST({w} AS BIGINT) AS width_bits, count(*) * {w // 8} AS raw_bytes, count(*) * {w // 8} AS enc_bytes FROM (WITH {raw(names)} SELECT * FROM s) GROUP BY series_id")
    return " UNION ALL ".join(parts)


_BP = f"SELECT series_id AS dataset_id, t // 128 AS b, count(*) AS n, {bits('bit_or(x)')} AS bits, sum(greatest(1, ({bits('x')} + 6) // 7)) AS tail FROM q GROUP BY series_id, t // 128"
RANKED = CORPUS
_RATIOS = f"ratios AS (SELECT *, raw_bytes / enc_bytes AS ratio FROM ({method_sizes(RANKED)}))"
_RANKS = "ranked AS (SELECT *, rank() OVER (PARTITION BY dataset_id, width_bits ORDER BY ratio DESC) + (count(*) OVER (PARTITION BY dataset_id, width_bits, ratio) - 1) / 2.0 AS rk FROM ratios)"
_MEAN = "means AS (SELECT method, width_bits, avg(rk) AS mean_rank, count(*) AS n FROM ranked GROUP BY ALL)"
def _paired(a: str, b: str) -> str:
    return f"pairs AS (SELECT a.dataset_id, a.width_bits, a.ratio AS a, b.ratio AS b FROM ratios a JOIN ratios b USING (dataset_id, width_bits) WHERE a.method = '{a}' AND b.method = '{b}')"


_SIGNED = """d AS (SELECT width_bits, round(a - b, 12) AS d FROM pairs WHERE round(a - b, 12) <> 0),
  r AS (SELECT width_bits, d, count(*) OVER (PARTITION BY width_bits, abs(d)) AS c, rank() OVER (PARTITION BY width_bits ORDER BY abs(d)) + (count(*) OVER (PARTITION BY width_bits, abs(d)) - 1) / 2.0 AS r FROM d),
  sums AS (SELECT width_bits, count(*) AS n, CAST(sum(CASE WHEN d > 0 THEN r ELSE 0 END) AS DOUBLE) AS plus, CAST(sum(CASE WHEN d < 0 THEN r ELSE 0 END) AS DOUBLE) AS minus, sum((c * c - 1) / 48.0) AS tie_term FROM r GROUP BY width_bits)"""
#: Two-sided normal p of z: 1 - erf(z / sqrt(2)) by its power series, 0 beyond 6.
_NORMAL_P = "CASE WHEN z > 6 THEN 0.0 ELSE round(1 - 2 / sqrt(pi()) * list_sum(list_transform(range(0, 120), lambda k: (CASE WHEN k % 2 = 0 THEN 1 ELSE -1 END) * exp((2 * k + 1) * ln(z / sqrt(2)) - lgamma(k + 1) - ln(2 * k + 1)))), 6) END"
_WINS = "SELECT width_bits, count(*) FILTER (a > b) AS wins, count(*) FILTER (a = b) AS ties, count(*) FILTER (a < b) AS losses, count(*) AS n FROM pairs GROUP BY width_bits"
_BARS = """cd AS (SELECT *, 2.850 * sqrt(6 * 7 / (6.0 * n)) AS cd FROM means),
  runs AS (SELECT a.width_bits, a.method, a.mean_rank AS first_rank, max(b.mean_rank) AS last_rank, string_agg(b.method, ',' ORDER BY b.mean_rank, b.method) AS methods, count(*) AS size FROM cd a JOIN cd b ON a.width_bits = b.width_bits AND b.mean_rank >= a.mean_rank AND b.mean_rank - a.mean_rank <= a.cd GROUP BY ALL)
  SELECT width_bits, round(min(first_rank), 6) AS first_rank, round(last_rank, 6) AS last_rank, arg_min(methods, first_rank) AS methods FROM runs WHERE size > 1 GROUP BY width_bits, last_rank"""
_QUAD = f"SELECT row_number() OVER (ORDER BY {', '.join(LINE_ORDER)}) - 1 AS t, CAST(l_quantity AS BIGINT) AS c0, CAST(round(l_discount * 100) AS BIGINT) AS c1, CAST(round(l_tax * 100) AS BIGINT) AS c2, CAST(l_linenumber AS BIGINT) AS c3 FROM lineitem"
_HOURLY = "SELECT date_trunc('hour', ts) AS hour, event_type, CAST(round(value * 100) AS BIGINT) AS c FROM events"
TYPES = ["click", "error", "purchase", "signup", "view"]


def _decoded(name: str, w: int, where: str = "TRUE") -> str:
    return f"WITH {prep([name], w)} SELECT t, x FROM q WHERE {where}"


def _gram(seconds: int) -> str:
    return f"SELECT event_type, CAST(epoch(ts) AS BIGINT) // {seconds} AS b, CAST(round(value * 100) AS BIGINT) AS c FROM events"


def _nmse(w: int, source: str, levels: int | None = None) -> str:
    top = float((1 << w) - 1 if levels is None else levels)
    return f"""SELECT name, round(avg((v - r) * (v - r)) / nullif(var_pop(v), 0), 6) AS nmse FROM (SELECT name, v, lo + coalesce(floor((v - lo) / nullif(hi - lo, 0) * {top}), 0) * (hi - lo) / {top} AS r
  FROM ({source}) JOIN (SELECT name, min(v) AS lo, max(v) AS hi FROM ({source}) GROUP BY name) USING (name)) GROUP BY name"""


FLOATS = (
    "SELECT 'events.value' AS name, value AS v FROM events UNION ALL SELECT 'orders.o_totalprice', o_totalprice FROM orders UNION ALL SELECT 'lineitem.l_extendedprice', l_extendedprice FROM lineitem "
    "UNION ALL SELECT 'part.p_retailprice', p_retailprice FROM part UNION ALL SELECT 'customer.c_acctbal', c_acctbal FROM customer UNION ALL SELECT 'supplier.s_acctbal', s_acctbal FROM supplier"
)
_SEGMENTS = (1024, 4096, 16384, 65536)

#: Variants of the learning forecaster, as options of ``adaptive``.
LEARNING = {
    "block, every other": {},
    "block, every sample": {"stride": 1},
    "sample": {"update": "sample", "stride": 1},
    "rate 1": {"shift": 0},
    "rate 1/4": {"shift": 2},
    "rate 1/16": {"shift": 4},
    "clamped": {"clamp": True},
    "rounded product": {"rounded": True},
    "case rule": {"case": True},
    "floor mean": {"floor": True},
}
ORACLES = {
    "q01_lag1_residuals": f"WITH {prep(['ev_value'], 16)}, {fixed(16, '0')} SELECT t, residual FROM r",
    "q02_double_delta": f"WITH {prep(['ev_ma64x2'], 16)}, {fixed(16, '65536')} SELECT t, residual FROM r",
    "q03_two_point_mean": f"WITH {prep(['ev_value'], 16)}, {fixed(16, '-32768')} SELECT t, residual FROM r",
    "q04_fixed_alpha_grid": f"WITH {prep(['ev_value', 'ev_walk', 'ev_ma64x2'], 16)}, g AS (SELECT q.series_id || ':' || n AS series_id, t, x, n * 16384 AS coef FROM q, (SELECT unnest(range(-2, 5)) AS n)), {fixed(16, 'coef', 'g')} SELECT series_id, CAST(sum(abs(residual)) AS BIGINT) AS total, count(*) FILTER (residual = 0) AS zeros FROM r GROUP BY series_id",
    "q05_adaptive_sample_residuals": f"WITH RECURSIVE s AS ({TYPED}), {quant(16)}, {cut()}, {adaptive(16, 'sample', source='c', stride=1)} SELECT {_WHOLE} AS series_id, {_NUMBER} * {SEGMENT} + t AS t, residual FROM f WHERE t >= 0",
    "q06_adaptive_block_residuals": f"WITH RECURSIVE s AS ({TYPED}), {quant(16)}, {cut()}, {adaptive(16, source='c')} SELECT {_WHOLE} AS series_id, {_NUMBER} * {SEGMENT} + t AS t, residual FROM f WHERE t >= 0",
    "q07_adaptive_final_alpha": f"WITH RECURSIVE {prep(['ev_value', 'ev_walk', 'ev_ma64x2'], 16)}, {cut()}, {adaptive(16, source='c')}, m AS (SELECT series_id, max(t) // 8 * 8 + CASE WHEN max(t) % 8 = 7 THEN 7 ELSE -1 END AS e FROM f GROUP BY series_id) SELECT {_WHOLE} AS series_id, {_NUMBER} * {SEGMENT} AS start, round((gain >> 1) / 65536.0, 6) AS alpha FROM f JOIN m USING (series_id) WHERE t = e",
    "q08_adaptive_native_vs_kernel": f"WITH RECURSIVE s AS ({TYPED}), {quant(16)}, {cut()}, {adaptive(16, source='c')} SELECT {_WHOLE} AS series_id, count(*) AS n, CAST(sum(abs(residual)) AS BIGINT) AS total, CAST(0 AS BIGINT) AS mismatches FROM f WHERE t >= 0 GROUP BY ALL",
    "q09_zigzag_roundtrip": f"WITH {prep(['ev_walk'], 16)}, {fixed(16, '0')} SELECT t, residual, {zig('residual')} AS z, residual AS back FROM r",
    "q10_block_widths": f"WITH {prep(UNIVARIATE, 8)}, {fixed(8, '0')}, {blocks(8)} SELECT series_id, block_id, n, CAST(bits AS BIGINT) AS bits, CAST(stored AS BIGINT) AS stored FROM b",
    "q11_stored_width_rule": f"SELECT w AS width_bits, CAST(bits AS BIGINT) AS bits, CAST(CASE WHEN bits >= w - 1 THEN w ELSE bits END AS BIGINT) AS stored, CAST(least(bits, w - 1) AS BIGINT) AS code, count(*) AS n FROM (SELECT w, {bits('v')} AS bits FROM (SELECT w, (CAST(round(l_extendedprice * 100) AS BIGINT) * l_orderkey) % CAST(pow(2, w) AS BIGINT) AS v FROM lineitem, (SELECT unnest([8, 16, 32])::BIGINT AS w))) GROUP BY ALL",
    "q12_header_bytes_by_group": f"WITH {prep(['li_day'], 16)}, {fixed(16, '0')}, {blocks(16)}, {slots()}, c AS (SELECT count(*) AS n FROM k) SELECT g AS group_size, CAST((n // g) * ((g * 4 + 7) // 8) + ((n % g) * 4 + 7) // 8 AS BIGINT) AS header_bytes FROM c, (SELECT unnest(range(1, 9)) AS g)",
    "q13_payload_layout_sizes": "WITH s AS (" + " UNION ALL ".join(f"SELECT 'c{j}' AS series_id, t, c{j} AS x FROM ({_QUAD})" for j in range(4)) + f"), {fixed(8, '0', 's')}, {blocks(8)}, y AS (SELECT block_id, sum(stored) AS w FROM b WHERE n = 8 GROUP BY block_id) SELECT 'column' AS layout, CAST(sum(w) AS BIGINT) AS payload_bytes FROM y UNION ALL SELECT 'row', CAST(sum((w + 7) // 8 * 8) AS BIGINT) FROM y",
    "q14_column_major_packed_bytes": f"WITH {prep(['ev_ma64x2'], 8)}, {fixed(8, '0')}, {blocks(8)}, y AS (SELECT block_id, stored, sum(CAST({zig('residual')} AS HUGEINT) << CAST((t % 8) * stored AS INTEGER)) AS v FROM r JOIN (SELECT block_id, stored FROM b WHERE n = 8) ON block_id = t // 8 GROUP BY ALL) SELECT block_id, coalesce(array_to_string(list_transform(range(0, stored), lambda i: lpad(lower(to_hex(CAST((v >> CAST(8 * i AS INTEGER)) % 256 AS BIGINT))), 2, '0')), ''), '') AS payload FROM y",
    "q15_zero_runs": f"WITH {prep(['li_day', 'ev_total'], 16)}, {fixed(16, '0')}, {blocks(16)}, {slots()} SELECT series_id, CAST(slot AS BIGINT) AS slot, first_block, n_blocks, CASE WHEN stored = 0 THEN 'run' ELSE 'data' END AS kind FROM k",
    "q16_encoded_size_speed": " UNION ALL ".join(f"SELECT * FROM (WITH {cut_lag1(UNIVARIATE, w)} SELECT {_WHOLE} AS series_id, CAST({w} AS BIGINT) AS width_bits, CAST(sum({_BODY}) AS BIGINT) AS body_bytes FROM z GROUP BY ALL)" for w in (8, 16)),
    "q17_encoded_size_balanced": f"SELECT series_id, enc_bytes AS body_bytes FROM ({learnt_sizes(['ev_value', 'ev_walk', 'ev_ma64x2', 'ord_total'], 16, True)})",
    "q19_roundtrip_speed": _decoded("ev_walk", 16),
    "q20_roundtrip_balanced": _decoded("ev_ma64x2", 16),
    "q21_roundtrip_ratio": _decoded("ev_total", 8),
    "q22_roundtrip_speed_huffman": _decoded("li_day", 8),
    "q23_decode_range_pruned": _decoded("ev_ma64x2", 16, "t >= 3000 AND t < 5500"),
    "q24_compressed_max": f"WITH {prep(UNIVARIATE, 16)} SELECT series_id, max(x) AS most FROM q GROUP BY series_id",
    "q25_compressed_min_count_sum": f"WITH {prep(UNIVARIATE, 8)} SELECT series_id, min(x) AS least, count(*) AS n, CAST(sum(x) AS BIGINT) AS total FROM q GROUP BY series_id",
    "q26_downsample_hourly": f"WITH {prep(['ev_walk'], 16)}, h AS (SELECT t, date_trunc('hour', ts) AS hour FROM {_EV}) SELECT CAST(epoch(hour) AS BIGINT) AS hour, min(x) AS least, max(x) AS most, CAST(sum(x) AS BIGINT) AS total, count(*) AS n FROM q JOIN h USING (t) GROUP BY hour",
    "q27_pairwise_corr": "WITH h AS (SELECT event_type, b, CAST(sum(c) AS DOUBLE) AS c FROM (" + _gram(86400) + ") GROUP BY ALL) SELECT a.event_type AS one, z.event_type AS other, round(corr(a.c, z.c), 6) AS corr FROM h a JOIN h z ON a.b = z.b AND a.event_type < z.event_type GROUP BY ALL",
    "q28_asof_align": "WITH e AS (SELECT event_id, ts, CAST(round(value * 100) AS BIGINT) AS c, event_type FROM events) SELECT p.event_id, v.c AS latest FROM (SELECT * FROM e WHERE event_type = 'purchase') p ASOF LEFT JOIN (SELECT * FROM e WHERE event_type = 'view') v ON p.ts >= v.ts",
    "q29_quantize_8": f"WITH {prep(['ev_value', 'ev_walk', 'ord_cum'], 8)} SELECT series_id, t, x FROM q",
    "q30_quantize_16": f"WITH {prep(['ev_value', 'ev_walk', 'ord_cum'], 16)} SELECT series_id, t, x FROM q",
    "q31_dequantize_error": " UNION ALL ".join(f"SELECT *, CAST({w} AS BIGINT) AS width_bits FROM ({_nmse(w, FLOATS)})" for w in (8, 16)),
    "q32_concat_interpolated": f"SELECT 'emb_' || label AS dataset_id, t, v FROM ({concatenated(_EMB)})",
    "q33_column_chunks": "WITH s AS (" + " UNION ALL ".join(f"SELECT {j} AS col, t, c{j} AS x FROM ({_QUAD})" for j in range(4)) + ") SELECT CAST(col AS BIGINT) AS col, t // 4096 AS chunk, count(*) AS n, sha256(upper(string_agg(lpad(to_hex(x), 2, '0'), '' ORDER BY t))) AS digest FROM s GROUP BY ALL",
    "q34_bp128_size": f"WITH {prep(UNIVARIATE, 16)} SELECT dataset_id AS series_id, CAST(sum(CASE WHEN n = 128 THEN 1 + 16 * bits ELSE tail END) AS BIGINT) AS enc_bytes FROM ({_BP}) GROUP BY dataset_id",
    "q35_pfor_size": f"""WITH {prep(['ev_value', 'ev_walk', 'ev_total'], 16)}, y AS (SELECT series_id, t // 128 AS b, {bits('x')} AS w FROM q), g AS (SELECT series_id, b, count(*) AS n, max(w) AS top, list(w) AS ws, sum(greatest(1, (w + 6) // 7)) AS tail FROM y GROUP BY ALL),
  o AS (SELECT series_id, b, top, base, len(list_filter(ws, lambda k: k > base)) AS c FROM (SELECT *, unnest(range(0, top + 1)) AS base FROM g WHERE n = 128)),
  best AS (SELECT * FROM o QUALIFY row_number() OVER (PARTITION BY series_id, b ORDER BY 128 * base + c * (top - base + 8), base) = 1),
  pool AS (SELECT series_id, sum((((c * w + 7) // 8 + 3) // 4) * 4) AS p FROM (SELECT series_id, top - base AS w, sum(c) AS c FROM best WHERE c > 0 GROUP BY ALL) GROUP BY series_id)
  SELECT series_id, CAST(own + coalesce(p, 0) AS BIGINT) AS enc_bytes FROM (SELECT series_id, sum(x) AS own FROM (SELECT series_id, 3 + c + 16 * base AS x FROM best UNION ALL SELECT series_id, tail FROM g WHERE n < 128) GROUP BY series_id) LEFT JOIN pool USING (series_id)""",
    "q36_simple8b_roundtrip": _decoded("ev_ma64", 16),
    "q38_byte_entropy": f"WITH {prep(UNIVARIATE, 8)}, c AS (SELECT series_id, x, count(*) AS c FROM q GROUP BY ALL), p AS (SELECT series_id, c, c / sum(c) OVER (PARTITION BY series_id) AS p FROM c) SELECT series_id, CAST(sum(c) AS BIGINT) AS bytes, round(-sum(p * log2(p)), 6) AS entropy_bits FROM p GROUP BY series_id",
    "q39_ratio_table": f"WITH {_RATIOS} SELECT dataset_id, method, width_bits, raw_bytes, enc_bytes, round(ratio, 6) AS ratio FROM ratios",
    "q40_ratio_boxplot": f"WITH {_RATIOS} SELECT method, width_bits, count(*) AS n, round(min(ratio), 6) AS least, round(quantile_cont(ratio, 0.25), 6) AS q1, round(quantile_cont(ratio, 0.5), 6) AS median, round(quantile_cont(ratio, 0.75), 6) AS q3, round(max(ratio), 6) AS most FROM ratios GROUP BY ALL",
    "q41_mean_ranks": f"WITH {_RATIOS}, {_RANKS}, {_MEAN} SELECT method, width_bits, round(mean_rank, 6) AS mean_rank, n FROM means",
    "q42_friedman": f"WITH {_RATIOS}, {_RANKS}, {_MEAN} SELECT width_bits, count(*) AS k, max(n) AS n, round(12.0 * max(n) / (count(*) * (count(*) + 1)) * (sum(mean_rank * mean_rank) - count(*) * (count(*) + 1) * (count(*) + 1) / 4.0), 6) AS chi2 FROM means GROUP BY width_bits",
    "q42_nemenyi": f"WITH {_RATIOS}, {_RANKS}, {_MEAN} SELECT a.width_bits, a.method, b.method AS other, round(abs(a.mean_rank - b.mean_rank), 6) AS difference, round(2.850 * sqrt(6 * 7 / (6.0 * a.n)), 6) AS cd, abs(a.mean_rank - b.mean_rank) > 2.850 * sqrt(6 * 7 / (6.0 * a.n)) AS differ FROM means a JOIN means b ON a.width_bits = b.width_bits AND a.method < b.method",
    "q43_wins": f"WITH {_RATIOS}, {_paired('double_delta', 'lag1')} {_WINS}",
    "q44_signed_ranks": f"WITH {_RATIOS}, {_paired('double_delta', 'lag1')}, {_SIGNED} SELECT width_bits, n, plus, minus FROM sums",
    "q43_wins_adaptive": f"WITH {_RATIOS}, {_paired('balanced', 'lag1')} {_WINS}",
    "q44_signed_ranks_adaptive": f"WITH {_RATIOS}, {_paired('balanced', 'lag1')}, {_SIGNED} SELECT width_bits, n, plus, minus FROM sums",
    "q44_wilcoxon_adaptive": f"WITH {_RATIOS}, {_paired('balanced', 'lag1')}, {_SIGNED}, zs AS (SELECT width_bits, n, least(plus, minus) AS w, abs(least(plus, minus) - n * (n + 1) / 4.0) / sqrt(n * (n + 1) * (2 * n + 1) / 24.0 - tie_term) AS z FROM sums) SELECT width_bits, n, w, {_NORMAL_P} AS p FROM zs",
    "q42_rank_groups": f"WITH {_RATIOS}, {_RANKS}, {_MEAN}, {_BARS}",
    "q45_noise_floor": " UNION ALL ".join(f"SELECT * FROM (WITH {prep(UNIVARIATE, w)}, {fixed(w, '0')} SELECT series_id, round(avg({bits(zig('residual'))}), 6) AS mean_bits, count(*) AS n, CAST({w} AS BIGINT) AS width_bits FROM r GROUP BY series_id)" for w in (8, 16)),
    "q46_bayes_error": f"WITH {prep(UNIVARIATE, 8)}, {fixed(8, '0')}, p AS (SELECT series_id, residual, lag(residual) {_BY} AS a FROM r), c AS (SELECT series_id, a, residual, count(*) AS c FROM p WHERE a BETWEEN -1 AND 1 AND residual BETWEEN -1 AND 1 GROUP BY ALL), m AS (SELECT series_id, a, max(c) AS best, sum(c) AS total FROM c GROUP BY ALL) SELECT series_id, CAST(sum(total) AS BIGINT) AS pairs, round(1 - sum(best) / sum(total), 6) AS bayes_error FROM m GROUP BY series_id",
    "q47_size_breakdown": "WITH a AS (" + " UNION ALL ".join(f"SELECT *, CAST({w} AS BIGINT) AS width_bits FROM (WITH {lag1_sizes(UNIVARIATE, w)} SELECT series_id, header_bytes, payload_bytes, run_bytes, tail_bytes, zero_blocks FROM z)" for w in (8, 16)) + ") SELECT coalesce(series_id, 'all') AS series_id, coalesce(CAST(width_bits AS VARCHAR), 'all') AS width_bits, " + ", ".join(f"CAST(sum({c}) AS BIGINT) AS {c}" for c in ("header_bytes", "payload_bytes", "run_bytes", "tail_bytes", "zero_blocks")) + " FROM a GROUP BY CUBE (series_id, width_bits)",
    "q49_spike_example": f"WITH q AS (SELECT 'x' AS series_id, row_number() OVER (ORDER BY ts, event_id) - 1 AS t, CAST(CASE WHEN event_type = 'error' THEN 255 ELSE 0 END AS BIGINT) AS x FROM events), {fixed(8, '0', out='r1')}, {fixed(8, '256', out='r2')}, a AS (SELECT 'raw' AS kind, {wrap('x', 8)} AS residual FROM q UNION ALL SELECT 'lag1', residual FROM r1 UNION ALL SELECT 'double_delta', residual FROM r2) SELECT kind, CAST({bits('o')} AS BIGINT) AS bits, touched FROM (SELECT kind, bit_or({zig('residual')}) AS o, count(*) FILTER (residual <> 0) AS touched FROM a GROUP BY kind)",
    "q50_widths_worked_example": f"SELECT z, n, CAST(bits AS BIGINT) AS bits, CAST(8 - bits AS BIGINT) AS leading_zeros, CAST(CASE WHEN bits >= 7 THEN 8 ELSE bits END AS BIGINT) AS stored FROM (SELECT z, n, {bits('z')} AS bits FROM (SELECT CAST(round(l_extendedprice * 100) AS BIGINT) % 256 AS z, count(*) AS n FROM lineitem GROUP BY ALL))",
    "q51_buffer_latency": "SELECT event_type, b AS buffer_bytes, d AS dims, CAST(8 AS BIGINT) AS width_bits, round(h, 6) AS hertz, round(b / (d * h), 3) AS seconds FROM (SELECT event_type, count(*) * 1e6 / (max(epoch_us(ts)) - min(epoch_us(ts))) AS h FROM events GROUP BY event_type), (VALUES (CAST(10000 AS BIGINT), CAST(9 AS BIGINT)), (8, 1)) AS v(b, d)",
    "q52_memory_model": "SELECT dims, hours, w AS width_bits, 8 * dims * w // 8 + dims * 4 * w // 8 AS bytes FROM (SELECT dims, count(*) AS hours FROM (SELECT count(DISTINCT user_id) AS dims FROM events GROUP BY CAST(floor(epoch(ts)) AS BIGINT) // 3600) GROUP BY dims), (SELECT unnest([8, 16])::BIGINT AS w)",
    "q53_power_bound": f"WITH {lag1_sizes(['ev_value', 'ev_total', 'ev_walk'], 8)} SELECT series_id, round(n / ({_BODY}), 6) AS ratio, round(30.0 / (n / ({_BODY})) + 0.05, 6) AS milliwatts FROM z",
    "q54_advisor": f"""WITH {prep(UNIVARIATE, 16)}, {fixed(16, '0')}, c AS (SELECT series_id, count(*) AS n, count(DISTINCT x) AS levels FROM q GROUP BY series_id), z AS (SELECT series_id, avg(CASE WHEN o = 0 THEN 1.0 ELSE 0.0 END) AS zero_share FROM (SELECT series_id, t // 8, bit_or({zig('residual')}) AS o FROM r GROUP BY ALL) GROUP BY series_id),
  k AS (SELECT series_id, avg(CAST(residual AS DOUBLE) * residual) AS a, avg(CAST(d AS DOUBLE) * d) AS b FROM (SELECT series_id, residual, {wrap(f'residual - coalesce(lag(residual) {_BY}, 0)', 16)} AS d FROM r) GROUP BY series_id)
  SELECT series_id, n, levels, round(zero_share, 6) AS zero_share, round(b / nullif(a, 0), 6) AS roughness, CASE WHEN zero_share > 0.5 OR levels < 64 THEN 'general' WHEN b < 1.5 * a THEN 'adaptive' ELSE 'lag1' END AS advice FROM c JOIN z USING (series_id) JOIN k USING (series_id)""",
    "q55_segment_ablation": " UNION ALL ".join(f"SELECT * FROM (WITH {raw(UNIVARIATE)}, {quant(16, 's', 'q0')}, q AS (SELECT series_id || '/' || t // {n} AS series_id, t % {n} AS t, x FROM q0), {fixed(16, '0')}, {blocks(16)}, {slots()}, {bodies(16)} SELECT split_part(series_id, '/', 1) AS series_id, CAST({n} AS BIGINT) AS segment_length, count(*) AS segments, CAST(sum({_BODY}) AS BIGINT) AS body_bytes FROM z GROUP BY ALL)" for n in _SEGMENTS),
    "q56_block_size_ablation": " UNION ALL ".join(f"SELECT * FROM (WITH {prep(RANKED, 16)}, {fixed(16, '0')}, {blocks(16, block=n)}, {slots(block=n)}, {bodies(16, block=n)} SELECT series_id, CAST({n} AS BIGINT) AS block, {_BODY} AS body_bytes FROM z)" for n in (4, 8, 16, 32, 64)),
    "q57_lowbit_nmse": " UNION ALL ".join(f"SELECT *, CAST({k} AS BIGINT) AS bits FROM ({_nmse(8, FLOATS, (1 << k) - 1)})" for k in (2, 4, 6)),
    "q58_stream_encode_equals_batch": "SELECT event_type AS series_id, row_number() OVER (PARTITION BY event_type ORDER BY ts, event_id) - 1 AS t, CAST(round(value * 100) AS BIGINT) AS x FROM events",
    "q59_stream_windows": "SELECT CAST(epoch(day) AS BIGINT) AS start, event_type AS series_id, CAST(sum(c) AS BIGINT) AS total, count(*) AS n FROM (SELECT date_trunc('day', ts) AS day, event_type, CAST(round(value * 100) AS BIGINT) AS c FROM events) WHERE day + INTERVAL 1 DAY <= (SELECT max(ts) - INTERVAL 1 HOUR FROM events) GROUP BY ALL",
    "q61_ar2_fit": f"WITH {raw(['ev_value', 'ev_walk', 'ev_ma64x2'])}, d AS (SELECT series_id, t, CAST(v - lag(v) {_BY} AS DOUBLE) AS d FROM s), p AS (SELECT series_id, d, lag(d) {_BY} AS p FROM d) SELECT series_id, count(*) AS n, round(sum(d * p) / sum(p * p), 6) AS alpha, round(1 + sum(d * p) / sum(p * p), 6) AS a, round(-sum(d * p) / sum(p * p), 6) AS b FROM p WHERE d IS NOT NULL AND p IS NOT NULL GROUP BY series_id",
    "q62_prefix_reconstruct": f"WITH {prep(['ev_walk', 'ev_ma64x2'], 16)} SELECT series_id, t, x AS lag1, x AS double_delta FROM q",
    "q65_udtf_decode": _decoded("ev_walk", 16),
    "q65_block_stats": f"WITH {prep(['li_day', 'ev_total'], 16)}, {cut()}, {fixed(16, '0', 'c')}, {blocks(16)}, {slots()} SELECT {_WHOLE} AS series_id, {_NUMBER} AS segment_id, CAST(slot AS BIGINT) AS slot, first_block, n_blocks, CASE WHEN stored = 0 THEN 'run' ELSE 'data' END AS kind FROM k",
    "q66_datasource_read": _decoded("ev_walk", 16, "t >= 2000 AND t < 4000"),
    "q71_header_group_bytes": " UNION ALL ".join(f"SELECT * FROM (WITH {cut_lag1(RANKED, 16, g)} SELECT {_WHOLE} AS series_id, CAST({g} AS BIGINT) AS group_size, CAST(sum({_BODY}) AS BIGINT) AS body_bytes FROM z GROUP BY ALL)" for g in range(1, 9)),
    "q67_huffman_kraft": "SELECT kind, count(DISTINCT symbol) AS symbols, count(*) AS total, CAST(2048 AS BIGINT) AS kraft_2048, TRUE AS within_a_bit FROM (SELECT 'price' AS kind, CAST(round(l_extendedprice * 100) AS BIGINT) % 256 AS symbol FROM lineitem UNION ALL SELECT 'quantity', CAST(l_quantity AS BIGINT) FROM lineitem UNION ALL SELECT 'flag', CAST(ascii(l_returnflag) AS BIGINT) FROM lineitem) GROUP BY kind",
    "q69_learning_ablation": " UNION ALL ".join(f"SELECT series_id, '{name}' AS variant, enc_bytes AS bytes FROM ({learnt_sizes(RANKED, 16, True, **options)})" for name, options in LEARNING.items()),
}
