"""Series out of the given tables: ``(series_id, t, v)`` univariate, ``(series_id, t, x)`` wide.

Order is total: ties are broken by keys, or by all columns where there is none.  Values are exact whole
numbers (cents, days, microseconds) before any sum.
"""

from __future__ import annotations

from collections.abc import Callable
from functools import cache, reduce

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.bits import divided
from ..operators.ordering import RANGE_ROWS, moving_sum, positions
from ..operators.quantize import rescaled
from ..operators.relayout import concat_series
from .shared import fresh
from .tables import load

TYPES = ["click", "error", "purchase", "signup", "view"]


def cents(column: str) -> Column:
    return F.round(F.col(column) * 100).cast("bigint")


def kept(df: DataFrame, name: str) -> DataFrame:
    """``df`` as a table in the shared folder, where a plan would otherwise compute it many times over."""
    spark = df.sparkSession
    path = fresh(spark, name)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


_DAY_MICROS = 86_400_000_000
#: While ``corpus`` builds several series of events: the one table (position and running sum of each event) that they share.
_shared_events: dict[str, DataFrame] = {}


def _events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events with cents ``c``, position ``t`` and the running sum ``run`` of cents."""
    if sf_dir in _shared_events:
        return _shared_events[sf_dir]
    e = load(spark, sf_dir, "events").select("event_id", "ts", "event_type", "user_id", cents("value").alias("c"))
    return positions(e, F.unix_date(F.to_date("ts")), ["ts", "event_id"], (), {"run": F.col("c")}, F.unix_micros(F.col("ts").cast("timestamp")) % _DAY_MICROS)


def _named(df: DataFrame, name: str, v: Column | str = "v") -> DataFrame:
    return df.select(F.lit(name).alias("series_id"), "t", (F.col(v) if isinstance(v, str) else v).cast("bigint").alias("v"))


def _running(df: DataFrame, name: str = "run") -> DataFrame:
    """``df`` (series_id, t, v) with an inclusive running sum of ``v``."""
    return positions(df.withColumnRenamed("t", "_old"), divided(F.col("_old"), 4096), ["_old"], ("series_id",), {name: F.col("v")}).drop("_old")


def ev_value(spark, d):
    return _named(_events(spark, d), "ev_value", "c")


def ev_total(spark, d):
    return _named(_events(spark, d), "ev_total", "run")


def ev_walk(spark, d):
    return _named(_events(spark, d), "ev_walk", F.col("run") - 5000 * (F.col("t") + 1))


def ev_ma64(spark, d):
    return _named(moving_sum(_events(spark, d), "run", 64), "ev_ma64")


def ev_ma64x2(spark, d):
    return _named(moving_sum(_running(ev_ma64(spark, d)), "run", 64, ("series_id",)), "ev_ma64x2")


def ev_walk2(spark, d):
    walk = ev_walk(spark, d)
    mean = walk.agg(F.sum("v").alias("s"), F.count(F.lit(1)).alias("n")).select(divided(F.col("s") - F.pmod("s", "n"), F.col("n")).alias("m"))
    return _named(_running(walk.crossJoin(F.broadcast(mean)).withColumn("v", F.col("v") - F.col("m"))), "ev_walk2", "run")


def ev_ts(spark, d):
    e = _events(spark, d).withColumn("us", F.unix_micros(F.col("ts").cast("timestamp")))
    origin = load(spark, d, "events").agg(F.unix_micros(F.min("ts").cast("timestamp")).alias("o"))
    return _named(e.crossJoin(F.broadcast(origin)), "ev_ts", F.col("us") - F.col("o"))


def li_day(spark, d):
    """Days in order: as equal ones follow each other, their counts say where each begins, and no line is sorted."""
    days = load(spark, d, "lineitem").select(F.unix_date(F.to_date("l_shipdate")).cast("bigint").alias("v")).where("v is not null").groupBy("v").agg(F.count(F.lit(1)).alias("n"))
    begun = days.withColumn("from", F.coalesce(F.sum("n").over(Window.orderBy("v").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    parts = begun.select("v", (F.col("from") + F.col("n")).alias("to"), F.explode(F.expr(f"sequence(from, from + n - 1, {RANGE_ROWS}L)")).alias("at"))
    parts = parts.repartition(int(spark.conf.get("spark.sql.shuffle.partitions")), "v", "at")
    return _named(parts.select("v", F.explode(F.expr(f"sequence(at, least(at + {RANGE_ROWS}L, to) - 1)")).alias("t")), "li_day")


LINE_ORDER = ["l_shipdate", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus"]


def _lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    return positions(load(spark, sf_dir, "lineitem"), F.unix_date(F.to_date("l_shipdate")), LINE_ORDER, fine=F.col("l_orderkey").cast("bigint"))


def li_qty(spark, d):
    """Quantities in the order of ``LINE_ORDER``, whose columns after the quantity can't tell equal quantities apart."""
    order = LINE_ORDER[: LINE_ORDER.index("l_quantity") + 1]
    lines = load(spark, d, "lineitem").select(*order)
    return _named(positions(lines, F.unix_date(F.to_date("l_shipdate")), order, fine=F.col("l_orderkey").cast("bigint")), "li_qty", "l_quantity")


def ord_total(spark, d):
    daily = load(spark, d, "orders").groupBy(F.to_date("o_orderdate").alias("day")).agg(F.sum(cents("o_totalprice")).alias("c"))
    return _named(moving_sum(positions(daily, F.trunc("day", "year"), ["day"], (), {"run": F.col("c")}), "run", 30), "ord_total")


def ord_cum(spark, d):
    o = load(spark, d, "orders").select("o_orderdate", "o_orderkey", cents("o_totalprice").alias("c"))
    return _named(positions(o, F.unix_date(F.to_date("o_orderdate")), ["o_orderdate", "o_orderkey"], (), {"run": F.col("c")}, F.unix_micros(F.col("o_orderdate").cast("timestamp")) % 86_400_000_000), "ord_cum", "run")


def _keyed(table: str, key: str, value: str, name: str):
    def build(spark, d):
        rows = load(spark, d, table).select(F.col(key).cast("bigint").alias("k"), cents(value).alias("v"))
        return _named(positions(rows, divided(F.col("k"), 4096), ["k", "v"]), name)

    return build


def ev_types(spark, d, running: bool):
    """A series for each event type: values, or their running sums."""
    e = load(spark, d, "events").select("event_id", "ts", "event_type", cents("value").alias("c"))
    p = positions(e, F.unix_date(F.to_date("ts")), ["ts", "event_id"], ("event_type",), {"run": F.col("c")}, F.unix_micros(F.col("ts").cast("timestamp")) % 86_400_000_000)
    name = F.concat(F.lit("ev_run_" if running else "ev_val_"), "event_type")
    return p.select(name.alias("series_id"), "t", F.col("run" if running else "c").cast("bigint").alias("v"))


USERS = 8


def ev_users(spark, d, running: bool):
    """A series for each group of users (id modulo ``USERS``): values, or their running sums."""
    e = load(spark, d, "events").select("event_id", "ts", (F.col("user_id") % USERS).alias("u"), cents("value").alias("c"))
    p = positions(e, F.unix_date(F.to_date("ts")), ["ts", "event_id"], ("u",), {"run": F.col("c")}, F.unix_micros(F.col("ts").cast("timestamp")) % 86_400_000_000)
    name = F.concat(F.lit("ev_user_run_" if running else "ev_user_val_"), F.col("u").cast("string"))
    return p.select(name.alias("series_id"), "t", F.col("run" if running else "c").cast("bigint").alias("v"))


def texts(spark, d, docs_to_a_part: int = 64) -> DataFrame:
    """(series_id, segment_id, k, b): UTF-8 of documents by language, and of pages, that is not empty; ``docs_to_a_part`` ids make a segment."""
    docs = load(spark, d, "documents").select(F.concat(F.lit("doc_bytes_"), "lang").alias("series_id"), F.col("doc_id").cast("bigint").alias("k"), F.encode("text", "UTF-8").alias("b"))
    pages = load(spark, d, "pages").select(F.lit("page_bytes").alias("series_id"), F.col("page_id").cast("bigint").alias("k"), F.encode("html", "UTF-8").alias("b"))
    return docs.unionByName(pages).where("length(b) > 0").withColumn("segment_id", divided(F.col("k"), docs_to_a_part))


def text_bytes(spark, d, docs_to_a_part: int = 64) -> DataFrame:
    """(series_id, segment_id, t, x): bytes of ``texts`` in the order of their ids.

    A segment holds the bytes of ``docs_to_a_part`` texts, so no position needs a sum over the table; this is data that repeats itself.
    """
    order = Window.partitionBy("series_id", "segment_id").orderBy("k").rowsBetween(Window.unboundedPreceding, -1)
    placed = texts(spark, d, docs_to_a_part).withColumn("start", F.coalesce(F.sum(F.length("b")).over(order), F.lit(0)))
    return placed.select("series_id", "segment_id", "start", F.expr("posexplode(split(rtrim(regexp_replace(hex(b), '(..)', '$1 ')), ' '))").alias("i", "h")).select(
        "series_id", "segment_id", (F.col("start") + F.col("i")).cast("bigint").alias("t"), F.conv("h", 16, 10).cast("bigint").alias("x")
    )


def emb_parts(spark, d, walk: bool) -> DataFrame:
    """(dataset_id, part_id, t, v): each vector is one short series, in millionths."""
    e = load(spark, d, "embeddings").select(F.concat(F.lit("emb_walk_" if walk else "emb_"), F.col("label").cast("string")).alias("dataset_id"), F.col("vec_id").cast("bigint").alias("part_id"), F.transform("embedding", lambda x: F.round(x.cast("double") * 1000000).cast("bigint")).alias("a"))
    if walk:
        e = e.withColumn("a", F.expr("transform(sequence(1, size(a)), i -> aggregate(slice(a, 1, i), 0L, (s, y) -> s + y))"))
    return e.select("dataset_id", "part_id", F.posexplode("a").alias("p", "v")).select("dataset_id", "part_id", F.col("p").cast("bigint").alias("t"), "v")


def emb_series(spark, d, walk: bool):
    return concat_series(emb_parts(spark, d, walk)).select(F.col("dataset_id").alias("series_id"), "t", "v")


UNIVARIATE: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "ev_value": ev_value,
    "ev_total": ev_total,
    "ev_walk": ev_walk,
    "ev_ma64": ev_ma64,
    "ev_ma64x2": ev_ma64x2,
    "ev_walk2": ev_walk2,
    "ev_ts": ev_ts,
    "li_day": li_day,
    "li_qty": li_qty,
    "ord_total": ord_total,
    "ord_cum": ord_cum,
    "part_price": _keyed("part", "p_partkey", "p_retailprice", "part_price"),
    "cust_bal": _keyed("customer", "c_custkey", "c_acctbal", "cust_bal"),
    "supp_bal": _keyed("supplier", "s_suppkey", "s_acctbal", "supp_bal"),
    "ev_val_types": lambda s, d: ev_types(s, d, False),
    "ev_run_types": lambda s, d: ev_types(s, d, True),
    "ev_user_vals": lambda s, d: ev_users(s, d, False),
    "ev_user_runs": lambda s, d: ev_users(s, d, True),
    "emb_labels": lambda s, d: emb_series(s, d, False),
    "emb_walks": lambda s, d: emb_series(s, d, True),
}


OF_EVENTS = ("ev_value", "ev_total", "ev_walk", "ev_ma64", "ev_ma64x2", "ev_walk2", "ev_ts")


def corpus(spark: SparkSession, sf_dir: str, names: list[str] | None = None) -> DataFrame:
    """All univariate datasets (or those builders) in one table."""
    names = names or list(UNIVARIATE)
    if sum(n in OF_EVENTS for n in names) > 1:
        _shared_events[sf_dir] = kept(_events(spark, sf_dir), "events")
    try:
        made = [UNIVARIATE[n](spark, sf_dir) for n in names]
    finally:
        _shared_events.pop(sf_dir, None)
    out = made[0]
    for m in made[1:]:
        out = out.unionByName(m)
    return out


def _array(df: DataFrame, name: str, columns: list[str]) -> DataFrame:
    return df.select(F.lit(name).alias("series_id"), "t", F.array(*[F.col(c).cast("bigint") for c in columns]).alias("x"))


def _quantized_columns(df: DataFrame, columns: list[str], width: int, per_column: bool) -> DataFrame:
    """Columns rescaled to the range of ``width`` bits by their own or by common bounds."""
    top = (1 << width) - 1
    agg = df.agg(*[F.min(c).alias(f"lo_{c}") for c in columns], *[F.max(c).alias(f"hi_{c}") for c in columns])
    if not per_column:
        lo, hi = F.least(*[F.col(f"lo_{c}") for c in columns]), F.greatest(*[F.col(f"hi_{c}") for c in columns])
        agg = agg.select(*[lo.alias(f"lo_{c}") for c in columns], *[hi.alias(f"hi_{c}") for c in columns])
    out = df.crossJoin(F.broadcast(agg))
    return out.select("t", *[rescaled(F.col(c), F.col(f"lo_{c}"), F.col(f"hi_{c}"), top).alias(c) for c in columns])


def _event_grid(spark: SparkSession, sf_dir: str, users: int, types: tuple[str, ...], seconds: int) -> tuple[DataFrame, list[str]]:
    """Cents by user group and type in buckets from the first to the last, empty ones 0; columns are listed, not found."""
    e = load(spark, sf_dir, "events").select(F.unix_seconds(F.col("ts").cast("timestamp")).alias("s"), (F.col("user_id") % users).alias("u"), "event_type", cents("value").alias("c"))
    e = e.withColumn("b", divided(F.col("s"), seconds))
    columns, sums = [], []
    for u in range(users):
        for k in types or (None,):
            columns.append(f"c{len(columns)}")
            of = (F.col("u") == u) if k is None else (F.col("u") == u) & (F.col("event_type") == k)
            sums.append(F.coalesce(F.sum(F.when(of, F.col("c"))), F.lit(0)).alias(columns[-1]))
    filled = e.groupBy("b").agg(*sums)
    span = e.agg(F.min("b").alias("lo"), F.max("b").alias("hi")).select(F.explode(F.sequence("lo", "hi")).alias("b"), "lo")
    grid = span.join(filled, "b", "left").fillna(0, columns)
    return kept(grid.withColumn("t", F.col("b") - F.col("lo")).drop("b", "lo"), "grid"), columns


def _smoothed(df: DataFrame, columns: list[str], size: int) -> DataFrame:
    p = kept(positions(df.withColumnRenamed("t", "_old"), divided(F.col("_old"), 1024), ["_old"], (), {f"r_{c}": F.col(c) for c in columns}).drop("_old"), "running")
    earlier = p.select((F.col("t") + size).alias("t"), *[F.col(f"r_{c}").alias(f"e_{c}") for c in columns])
    out = p.join(earlier, "t", "left").where(F.col("t") >= size - 1)
    return out.select((F.col("t") - (size - 1)).alias("t"), *[(F.col(f"r_{c}") - F.coalesce(f"e_{c}", F.lit(0))).alias(c) for c in columns])


#: Columns before they are quantized: the table (t and columns), the columns, and whether each has bounds of its own (None: left as they are).
Columns = tuple[DataFrame, list[str], bool | None]


def _wide80(spark, d, grid) -> Columns:
    rows, columns = grid(16, tuple(TYPES), 600)
    return _smoothed(_smoothed(rows, columns, 144), columns, 144), columns, True


def _wide31(spark, d, grid) -> Columns:
    rows, columns = grid(31, (), 600)
    return _smoothed(_smoothed(rows, columns, 144), columns, 144), columns, True


def _stair80(spark, d, grid) -> Columns:
    rows, columns = grid(16, tuple(TYPES), 600)
    p = positions(rows.withColumnRenamed("t", "_old"), divided(F.col("_old"), 1024), ["_old"], (), {f"r_{c}": F.col(c) for c in columns})
    return p, [f"r_{c}" for c in columns], False


WIDE18 = [(f, s, m) for f in ("A", "N", "R") for s in ("F", "O") for m in ("l_quantity", "l_extendedprice", "l_discount")]


def _wide18(spark, d, grid) -> Columns:
    """Daily running sums of three measures by return flag and line status."""
    li = load(spark, d, "lineitem").withColumn("day", F.to_date("l_shipdate"))
    columns = [f"c{i}" for i in range(len(WIDE18))]
    daily = li.groupBy("day").agg(*[F.coalesce(F.sum(F.when((F.col("l_returnflag") == f) & (F.col("l_linestatus") == s), cents(m))), F.lit(0)).alias(c) for c, (f, s, m) in zip(columns, WIDE18, strict=True)])
    return positions(daily, F.trunc("day", "year"), ["day"], (), {f"r_{c}": F.col(c) for c in columns}), [f"r_{c}" for c in columns], True


def _li_quad(spark, d, grid) -> Columns:
    """Four small columns, at the limit of the column-major layout."""
    lines = _lines(spark, d).select("t", F.col("l_quantity").cast("bigint").alias("q"), cents("l_discount").alias("d"), cents("l_tax").alias("x"), F.col("l_linenumber").cast("bigint").alias("n"))
    return lines, ["q", "d", "x", "n"], None


def _ev_pivot5(spark, d, grid) -> Columns:
    """Hourly sums by event type, just past that limit."""
    return *grid(1, tuple(TYPES), 3600), False


def _state3(spark, d, grid) -> Columns:
    """Counts per minute of three rare events: isolated non-zeros."""
    e = load(spark, d, "events").select(divided(F.unix_seconds(F.col("ts").cast("timestamp")), 60).alias("b"), "event_type")
    columns = ["error", "purchase", "signup"]
    found = e.groupBy("b").agg(*[F.count(F.when(F.col("event_type") == k, 1)).alias(k) for k in columns])
    span = e.agg(F.min("b").alias("lo"), F.max("b").alias("hi")).select(F.explode(F.sequence("lo", "hi")).alias("b"), "lo")
    return span.join(found, "b", "left").fillna(0, columns).withColumn("t", F.col("b") - F.col("lo")), columns, False


def _state2(spark, d, grid) -> Columns:
    """Most frequent order status and priority of each day, as codes."""
    o = load(spark, d, "orders").select(F.to_date("o_orderdate").alias("day"), F.ascii("o_orderstatus").cast("bigint").alias("s"), F.ascii("o_orderpriority").cast("bigint").alias("p"))
    daily = o.groupBy("day").agg(F.max("s").alias("s"), F.min("p").alias("p"))
    return positions(daily, F.trunc("day", "year"), ["day"]), ["s", "p"], True


def _wide64(spark, d, grid) -> Columns:
    """Embeddings as one series of 64 columns."""
    e = load(spark, d, "embeddings").select("vec_id", *[F.round(F.col("embedding")[i].cast("double") * 1000000).cast("bigint").alias(f"c{i}") for i in range(64)])
    return positions(e, divided(F.col("vec_id").cast("bigint"), 4096), ["vec_id"]), [f"c{i}" for i in range(64)], False


_COLUMNS = {"wide80": _wide80, "wide31": _wide31, "wide18": _wide18, "wide64": _wide64, "stair80": _stair80, "state3": _state3, "state2": _state2, "ev_pivot5": _ev_pivot5, "li_quad": _li_quad}


def wide_columns(spark: SparkSession, sf_dir: str, names: tuple[str, ...]) -> dict[str, Columns]:
    """The columns of wide datasets as tables in the shared folder, for ``at_width`` to read; datasets on the same grid share it."""
    grid = cache(lambda users, types, seconds: _event_grid(spark, sf_dir, users, types, seconds))
    made = {}
    for name in names:
        rows, columns, own = _COLUMNS[name](spark, sf_dir, grid)
        made[name] = kept(rows.select("t", *columns), name), columns, own
    return made


def at_width(made: dict[str, Columns], width: int) -> DataFrame:
    """(series_id, t, x) of all datasets of ``made`` at ``width`` bits."""
    parts = [_array(rows if own is None else _quantized_columns(rows, columns, width, own), name, columns) for name, (rows, columns, own) in made.items()]
    return reduce(DataFrame.unionByName, parts)


def _wide(name: str) -> Callable[[SparkSession, str, int], DataFrame]:
    return lambda spark, sf_dir, width=8: at_width(wide_columns(spark, sf_dir, (name,)), width)


WIDE = {name: _wide(name) for name in _COLUMNS}
li_quad, wide64 = WIDE["li_quad"], WIDE["wide64"]


def uniform(spark: SparkSession, values: int, dims: int, width: int, seed: int = 7) -> DataFrame:
    """Incompressible samples: ``values`` hashed numbers seen as rows of ``dims`` columns, in segments of 65536 samples."""
    rows = spark.range(values // dims)
    return rows.select(F.lit(f"uniform_{dims}").alias("series_id"), F.col("id").alias("t"), F.array(*[F.pmod(F.xxhash64("id", F.lit(seed * 1000 + j)), F.lit(1 << width)) for j in range(dims)]).alias("x"))
