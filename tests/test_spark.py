"""Plans over the given tables: anchors, refusals, parity with DuckDB on the smallest scale."""

import pytest
from pyspark.errors import PythonException
from pyspark.sql import functions as F

from seriespack.operators import blocks, codec, forecast
from seriespack.operators import measures as M
from seriespack.operators import quantize as Q
from seriespack.operators.options import Options
from seriespack.operators.relayout import null_policy, wide
from seriespack.plans import experiments, oracles, queries, surfaces  # noqa: F401  (importing registers queries)
from seriespack.sources import builders as S

#: Exact body sizes on the 0.01 scale: lag1 and adaptive, 8 and 16 bits.
ANCHORS = {"ev_value": (10315, 10201, 20320, 20197), "ev_walk": (5099, 5191, 15065, 15058), "ev_walk2": (2031, 2031, 8000, 7786), "ord_total": (1867, 1862, 4239, 4236)}


def test_anchors(spark):
    raw = queries.values(spark, "/root/testdata/sf0.01", list(ANCHORS))
    got = {}
    for w in (8, 16):
        q = Q.quantize(raw, w)
        native = {r.series_id: r.body_bytes for r in blocks.body_sizes(forecast.lag1(q, w), Options(width_bits=w)).collect()}
        for p in ("speed", "balanced"):
            for r in codec.encode(wide(q), p, w, segment_length=1 << 40).select("series_id", "body_bytes").collect():
                got.setdefault(r.series_id, []).append(r.body_bytes)
                assert p == "balanced" or native[r.series_id] == r.body_bytes
    assert {k: tuple(v) for k, v in got.items()} == ANCHORS


@pytest.mark.parametrize("name", ["q01_lag1_residuals", "q06_adaptive_block_residuals", "q15_zero_runs", "q24_compressed_max", "q28_asof_align", "q35_pfor_size", "q65_block_stats", "q66_datasource_read"])
def test_parity(spark, small, duck, name):
    got = sorted(tuple(r[c] for c in sorted(r.__fields__)) for r in queries.QUERIES[name](spark, small).collect()) if name != "q28_asof_align" else None
    want = duck(small).execute(oracles.ORACLES[name]).df()
    if got is None:
        got = {r.event_id: r.latest for r in queries.QUERIES[name](spark, small).collect()}
        assert got == {a: b for a, b in duck(small).execute(oracles.ORACLES[name]).fetchall()}
    else:
        assert got == sorted(map(tuple, want[sorted(want.columns)].astype(object).itertuples(index=False)))


def test_adaptive_queries_take_whole_series(spark, duck):
    sf = "/root/testdata/sf0.01"
    sizes = dict(duck(sf).execute(f"SELECT series_id, count(*) FROM ({oracles.TYPED}) GROUP BY ALL").fetchall())
    for name in ("q05_adaptive_sample_residuals", "q08_adaptive_native_vs_kernel"):
        got, want = queries.QUERIES[name](spark, sf), duck(sf).execute(oracles.ORACLES[name])
        columns = [d[0] for d in want.description]
        rows = want.fetchall()
        assert sorted(map(tuple, got.select(*columns).collect())) == sorted(rows)
        assert sum(r[columns.index("n")] for r in rows) == sum(sizes.values()) if "n" in columns else len(rows) == sum(sizes.values())


def test_encode_is_one_exchange_and_decode_none(spark, small):
    path = queries.fresh(spark, "plan")
    queries.write_segments(codec.encode(wide(queries.series(spark, small, ["ev_walk"], 16)), "speed", 16), path)
    plan = codec.decode(spark.read.parquet(path), 0, 100)._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan and "PushedFilters" in plan and "LessThan(t_start,100)" in plan


def test_edges(spark):
    empty = spark.createDataFrame([], "series_id string, t bigint, x array<bigint>")
    assert codec.encode(empty, "speed", 8).count() == 0
    one = spark.createDataFrame([("a", 0, [5])], "series_id string, t bigint, x array<bigint>")
    assert codec.decode(codec.encode(one, "ratio", 8)).collect()[0].x == [5]
    bad = spark.createDataFrame([("a", 0, [None])], "series_id string, t bigint, x array<bigint>")
    with pytest.raises(PythonException):
        codec.encode(bad, "speed", 8).collect()
    mixed = spark.createDataFrame([("a", 0, [1]), ("a", 1, [1, 2])], "series_id string, t bigint, x array<bigint>")
    with pytest.raises(PythonException):
        codec.encode(mixed, "speed", 8).collect()
    nulls = spark.createDataFrame([("a", 0, None), ("a", 1, 4), ("a", 2, None)], "series_id string, t bigint, v bigint")
    assert [r.v for r in null_policy(nulls, "carry_forward").orderBy("t").collect()] == [0, 4, 4]
    assert null_policy(nulls, "drop").count() == 1
    flat = spark.createDataFrame([("a", 0, 3), ("a", 1, 3)], "series_id string, t bigint, v bigint")
    assert {r.x for r in Q.quantize(flat, 8).collect()} == {0}


def test_damage_is_found(spark, small):
    s = codec.encode(wide(queries.series(spark, small, ["ev_walk"], 16)), "speed", 16)
    with pytest.raises(PythonException):
        codec.decode(s.withColumn("crc", F.col("crc") + 1)).count()


def test_bodies_do_not_depend_on_partitions(spark, small):
    q = wide(queries.series(spark, small, ["ev_walk", "ev_total"], 16))
    a = {(r.series_id, r.segment_id): bytes(r.body) for r in codec.encode(q.repartition(1), "ratio", 16, segment_length=300).collect()}
    b = {(r.series_id, r.segment_id): bytes(r.body) for r in codec.encode(q.repartition(7), "ratio", 16, segment_length=300).collect()}
    assert a == b


def test_statistics(spark):
    pairs = spark.createDataFrame([(str(i), 8, 1.0 + d, 1.0) for i, d in enumerate((0.1, 0.2, 0.3, 0.4, 0.5, -0.05))], "dataset_id string, width_bits bigint, a double, b double")
    r = M.wilcoxon(pairs).collect()[0]
    assert (r.n, r.w, round(r.p, 6)) == (6, 1.0, 0.0625)
    assert M.exact_p(5, 0) == 2 / 32
    ties = spark.createDataFrame([("d", m, 8, v) for m, v in (("a", 2.0), ("b", 2.0), ("c", 1.0))], "dataset_id string, method string, width_bits bigint, ratio double")
    assert {r.method: r["rank"] for r in M.ranks(ties).collect()} == {"a": 1.5, "b": 1.5, "c": 3.0}
    front = spark.createDataFrame([("d", 8, "a", 2.0, 1.0), ("d", 8, "b", 1.0, 2.0), ("d", 8, "c", 1.0, 1.0)], "dataset_id string, width_bits bigint, method string, ratio double, speed double")
    assert {r.method: r.on_front for r in M.pareto(front).collect()} == {"a": True, "b": True, "c": False}


def test_comparison_holds_ten_methods_on_the_whole_corpus(spark, small, monkeypatch):
    made = queries.compared(spark, small)
    monkeypatch.setattr(queries, "compared", lambda *_: made)
    of = {n: queries.QUERIES[n](spark, small).collect() for n in queries.QUERIES if n.endswith("_ten")}
    assert len(of) == 6
    methods = {"bp128", "pfor", "simple8b", "snappy", "zstd", "lz4", "zlib", "speed", "balanced", "ratio"}
    names = {r.series_id for r in S.corpus(spark, small, list(S.UNIVARIATE)).select("series_id").distinct().collect()}
    assert len(names) >= len(S.UNIVARIATE)
    table = of["q39_ratio_table_ten"]
    assert sorted((r.dataset_id, r.method, r.width_bits) for r in table) == sorted((n, m, w) for n in names for m in methods for w in (8, 16))
    assert {(r.k, r.n) for r in of["q42_friedman_ten"]} == {(10, len(names))}
    assert len(of["q41_mean_ranks_ten"]) == len(of["q40_ratio_boxplot_ten"]) == 20 and len(of["q42_nemenyi_ten"]) == 90
    assert all(r.cd > 0 for r in of["q42_nemenyi_ten"])
    assert len(names) == 60
    # a bar holds methods whose mean ranks lie within the critical difference
    ranks = {(r.width_bits, r.method): r.mean_rank for r in of["q41_mean_ranks_ten"]}
    cd = {r.width_bits: r.cd for r in of["q42_nemenyi_ten"]}
    for r in of["q42_rank_groups_ten"]:
        inside = [ranks[r.width_bits, m] for m in r.methods.split(",")]
        assert (min(inside), max(inside)) == (r.first_rank, r.last_rank) and r.last_rank - r.first_rank <= cd[r.width_bits] + 1e-6


def test_more_methods_than_the_table_are_refused(spark):
    rows = [("d", f"m{i}", 8, 1.0 + i) for i in range(21)]
    ratios = spark.createDataFrame(rows, "dataset_id string, method string, width_bits bigint, ratio double")
    assert M.nemenyi(ratios.where("ratio <= 20")).count() == 190
    with pytest.raises(Exception, match="2 to 20 methods"):
        M.nemenyi(ratios).collect()


def test_one_long_and_many_short_segments_stay_small():
    import tracemalloc

    import numpy as np

    from seriespack.operators.options import preset

    o = preset("speed", 16)
    segments = [np.arange(65_536, dtype=np.int64).reshape(-1, 1), *[np.arange(8, dtype=np.int64).reshape(-1, 1)] * 20_000]
    tracemalloc.start()
    made = codec.pack_many(segments, o)
    back = codec.unpack_many([(*m, len(x), 1) for m, x in zip(made, segments, strict=True)], o)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert all((a == b).all() for a, b in zip(segments, back, strict=True)) and peak < 200 << 20


def test_parts_of_a_series_join_up(spark):
    """Neighbours, running sums and runs do not depend on where a series is parted."""
    from seriespack.operators.ordering import neighbours, prefix_sums

    rows = [("a", t, (t // 23) % 5 + (t % 7 == 0)) for t in range(500)]
    x = spark.createDataFrame(rows, "series_id string, t bigint, x bigint")
    got = prefix_sums(neighbours(x, {"one": ("x", 1), "two": ("x", 2)}, ("series_id",), part=64), "x", "total", ("series_id",), part=64)
    v = [r[2] for r in rows]
    want = [(t, v[t - 1] if t else None, v[t - 2] if t > 1 else None, sum(v[: t + 1])) for t in range(500)]
    assert sorted((r.t, r.one, r.two, r.total) for r in got.collect()) == want


def test_nulls_are_interpolated(spark):
    rows = [("a", t, v) for t, v in enumerate((None, 10, None, None, 40, None))]
    x = spark.createDataFrame(rows, "series_id string, t bigint, v bigint")
    assert [(r.t, r.v) for r in null_policy(x, "interpolate").orderBy("t").collect()] == [(1, 10), (2, 20), (3, 30), (4, 40)]


def test_builders_have_dense_positions(spark, small):
    for name in ("ev_ma64x2", "li_day", "part_price"):
        t = [r.t for r in S.UNIVARIATE[name](spark, small).select("t").orderBy("t").collect()]
        assert t == list(range(len(t)))


def test_rescaling_passes_64_bits(spark):
    """A range whose product with the levels has more than 64 bits, as running sums of large tables have."""
    from seriespack.operators import quantize as Q

    top = (1 << 63) - 1
    rows = [("wide", v) for v in (-top, -5, 0, 3, top)] + [("near", v) for v in (0, 1, 10**15, 223_000_000_000_001, 2 * 10**15)] + [("flat", 7)]
    x = spark.createDataFrame(rows, "series_id string, v bigint")
    for w in (8, 16):
        got = {(r.series_id, r.v): r.x for r in Q.quantize(x, w).collect()}
        for name, v in rows:
            mine = [b for a, b in rows if a == name]
            assert got[name, v] == (v - min(mine)) * ((1 << w) - 1) // max(max(mine) - min(mine), 1)


def test_the_learnt_size_is_of_the_whole_series(spark):
    import numpy as np

    from seriespack.operators.options import preset

    rng, o = np.random.default_rng(3), preset("balanced", 16)
    made = {f"s{i}": np.cumsum(rng.integers(-3, 4, n)) % 65536 for i, n in enumerate((1, 30, 25_000))}
    x = spark.createDataFrame([(k, t, int(v)) for k, vs in made.items() for t, v in enumerate(vs)], "series_id string, t bigint, x bigint").repartition(7)
    got = {r.series_id: r.enc_bytes for r in codec.whole_sizes(x, o).collect()}
    assert got == {k: len(codec.pack_many([v.reshape(-1, 1).astype(np.int64)], o)[0][0]) for k, v in made.items()}


def test_packed_blocks_do_not_depend_on_pieces(spark, small, duck, monkeypatch):
    whole = queries.by_kernel
    monkeypatch.setattr(queries, "by_kernel", lambda df, make, ddl: whole(df, make, ddl, 64))
    got = sorted(map(tuple, queries.QUERIES["q14_column_major_packed_bytes"](spark, small).select("block_id", "payload").collect()))
    assert got == sorted(duck(small).execute(f"SELECT block_id, payload FROM ({oracles.ORACLES['q14_column_major_packed_bytes']})").fetchall())


def test_streams_keep_large_amounts(spark, small, tmp_path):
    """Cents of more than 16 bits, and negative ones, come out as they went in; a width that is too small is refused."""
    from seriespack.streaming import encoder

    amounts = F.when(F.col("event_id") % 50 == 0, F.col("value") + 700).when(F.col("event_id") % 50 == 1, -F.col("value")).otherwise(F.col("value"))
    spark.read.parquet(f"{small}/events.parquet").withColumn("value", amounts).write.parquet(f"{tmp_path}/events.parquet")
    want = sorted((r.event_type, r.c) for r in spark.read.parquet(f"{tmp_path}/events.parquet").select("event_type", S.cents("value").alias("c")).collect())
    assert max(c for _, c in want) > 65535
    for name in ("q58_stream_encode_equals_batch", "q60_stream_idle_flush"):
        assert sorted((r.series_id, r.x) for r in queries.QUERIES[name](spark, str(tmp_path)).collect()) == want
    with pytest.raises(Exception, match="don't fit 16 bits"):
        queries._stream(spark, str(tmp_path), lambda s: encoder.encode_stream(s, Options(width_bits=16), 256), "narrow").count()


def test_byte_series_never_make_a_row_of_a_byte(spark, small):
    """Sizes as those of segments built byte by byte, out of a plan that handles whole texts."""
    from seriespack.operators.options import preset

    made = queries.QUERIES["q75_byte_series"](spark, small)
    assert "explode" not in made._jdf.queryExecution().optimizedPlan().toString().lower()
    got = {(r.series_id, r.method): (r.raw_bytes, r.enc_bytes) for r in made.collect()}
    name = min(k for k, _ in got)
    x = S.text_bytes(spark, small).where(F.col("series_id") == name)
    for p in ("speed", "balanced", "ratio"):
        want = codec.encode(x.select("series_id", "segment_id", "t", F.array("x").alias("x")), preset(p, 8)).agg(F.sum("raw_bytes"), F.sum("body_bytes")).first()
        assert got[name, p] == tuple(want)


@pytest.mark.parametrize("name", ["q11_stored_width_rule", "q49_spike_example", "q50_widths_worked_example", "q51_buffer_latency", "q52_memory_model", "q53_power_bound", "q67_huffman_kraft"])
def test_examples_are_of_a_given_table(spark, small, duck, name):
    made, want = queries.QUERIES[name](spark, small), duck(small).execute(oracles.ORACLES[name])
    assert made.inputFiles()
    columns = [c[0] for c in want.description]
    assert sorted(map(tuple, made.select(*columns).collect())) == sorted(want.fetchall())
    if name == "q49_spike_example":
        assert {r.kind: r.bits for r in made.collect()} == {"raw": 1, "lag1": 2, "double_delta": 3}


@pytest.mark.parametrize("name", ["q72_speed_by_columns", "q83_forecaster_speed"])
def test_speeds_are_of_a_given_table(spark, small, name):
    assert queries.QUERIES[name](spark, small).inputFiles()


def test_forecasters_are_timed_on_all_bits_in_their_columns(spark, small, monkeypatch):
    """Every byte of every float passes at either width, padding left out, in as many columns as a row says; no seconds but the columns are told."""
    monkeypatch.setattr(experiments, "best_of", lambda reps, *steps: [[float(step(steps[0](None)).shape[1])] for step in steps])
    monkeypatch.setattr(M, "timing_spread", lambda timing: timing)
    got = experiments.q83_forecaster_speed(spark, small).collect()
    stored = 4 * spark.read.parquet(f"{small}/embeddings.parquet").agg(F.sum(F.size("embedding"))).head()[0]
    assert len(got) == 64 and {r.bytes for r in got} == {stored}
    assert all(r.ns == r.dims * 10**9 for r in got)


@pytest.mark.parametrize("w", [8, 16])
def test_all_bits_of_floats_are_samples(w):
    import numpy as np
    import pandas as pd

    given = [np.array([0.25, -1e-9, 3e38], np.float32), np.array([-0.0, np.inf, 123456.789], np.float32)]
    samples = queries.all_bits(pd.DataFrame({"vec_id": [7, 3], "v": given}), w)
    assert samples.dtype == np.int64 and samples.min() >= 0 and samples.max() < 1 << w
    back = samples.reshape(32 // w, -1).T.astype(f"u{w // 8}").copy().view(np.uint32).ravel()
    assert back.tolist() == np.concatenate(given[::-1]).view(np.uint32).tolist()


@pytest.mark.parametrize("part", [1, 4, 7, 1 << 16])
def test_zero_runs_go_on_over_parts(spark, part):
    """Maximal runs, however a series is parted: within a part, over an edge, over several parts, at both ends."""
    stored = {"a": [0] * 9 + [3, 0, 0, 5, 0, 4, 0, 0, 0, 0, 0, 0, 0, 1, 0], "b": [2, 0, 0, 0, 0, 7], "c": [0] * 8, "d": [1, 1]}
    rows = [(k, i, v) for k, values in stored.items() for i, v in enumerate(values)]
    got = blocks.zero_runs(spark.createDataFrame(rows, "series_id string, block_id bigint, stored bigint"), part=part)
    assert sorted(map(tuple, got.select("series_id", "first_block", "n_blocks").collect())) == [("a", 0, 9), ("a", 10, 2), ("a", 13, 1), ("a", 15, 7), ("a", 23, 1), ("b", 1, 4), ("c", 0, 8)]


def test_block_sizes_share_one_pass_over_the_samples(spark, small):
    """Blocks of all lengths add up from those of four, which are made once: only blocks of width 0 pass windows after that."""
    plan = queries.QUERIES["q56_block_size_ablation"](spark, small)._jdf.queryExecution().optimizedPlan().toString()
    assert "lag(x" not in plan and plan.count("Window [row_number()") == 5


def test_whole_sizes_of_two_columns_come_in_pieces(spark, monkeypatch):
    """Both widths of a series in one pass, over edges of parts and pieces; the task that sizes a series gets pieces, no row for each sample."""
    import numpy as np

    from seriespack.operators.options import preset

    monkeypatch.setattr(codec, "PART", 3000)
    rng, o = np.random.default_rng(5), {f"x{w}": preset("balanced", w) for w in (8, 16)}
    made = {f"s{i}": np.cumsum(rng.integers(-3, 4, n)) % 65536 for i, n in enumerate((5, 2048, 20_000))}
    x = spark.createDataFrame([(k, t, int(v) >> 8, int(v)) for k, vs in made.items() for t, v in enumerate(vs)], "series_id string, t bigint, x8 bigint, x16 bigint").repartition(7)
    sizes = codec.whole_sizes(x, o)
    assert sizes._jdf.queryExecution().optimizedPlan().toString().count("MapInArrow") == 2
    want = {(k, c): len(codec.pack_many([(v >> (16 - p.width_bits)).reshape(-1, 1).astype(np.int64)], p)[0][0]) for k, v in made.items() for c, p in o.items()}
    assert {(r.series_id, r.column): r.enc_bytes for r in sizes.collect()} == want


def test_whole_sizes_of_all_methods_come_in_pieces(spark, monkeypatch):
    """Forecasters without a state and binary packing ride along with the learner: no window over samples, no row for a block."""
    import numpy as np

    from seriespack.operators import baselines
    from seriespack.operators.options import preset

    monkeypatch.setattr(codec, "PART", 3000)
    rng = np.random.default_rng(6)
    of = {w: {m: Options(width_bits=w, forecaster="fixed", coef_num=c) for m, c in queries.coefficients(w).items()} | {"balanced": preset("balanced", w), "bp128": None} for w in (8, 16)}
    made = {f"s{i}": np.cumsum(rng.integers(-3, 4, n) * (rng.random(n) < 0.1)) % 65536 for i, n in enumerate((1, 130, 20_003))}
    x = spark.createDataFrame([(k, t, int(v) >> 8, int(v)) for k, vs in made.items() for t, v in enumerate(vs)], "series_id string, t bigint, x8 bigint, x16 bigint").repartition(7)
    sizes = codec.method_sizes(x, {f"x{w}": m for w, m in of.items()})
    assert "Window" not in sizes._jdf.queryExecution().optimizedPlan().toString()
    want = {}
    for k, v in made.items():
        for w, methods in of.items():
            column = (v >> (16 - w)).astype(np.int64)
            want |= {(k, f"x{w}", m): (len(v), len(codec.pack_many([column.reshape(-1, 1)], o)[0][0] if o else baselines.bp128_encode(column))) for m, o in methods.items()}
    assert {(r.series_id, r.column, r.method): (r.n_samples, r.enc_bytes) for r in sizes.collect()} == want


def test_lines_are_ordered_by_what_tells_them_apart(spark, small, monkeypatch):
    """Ship days need no order of lines at all, quantities none by the columns after them; both are those of all lines in order."""
    monkeypatch.setattr(S, "RANGE_ROWS", 2)
    lines = spark.read.parquet(f"{small}/lineitem.parquet").selectExpr("*", "unix_date(to_date(l_shipdate)) day").orderBy("day", *S.LINE_ORDER).collect()
    for name, column in (("li_day", "day"), ("li_qty", "l_quantity")):
        made = S.UNIVARIATE[name](spark, small)
        assert [(r.t, r.v) for r in made.orderBy("t").collect()] == [(t, int(r[column])) for t, r in enumerate(lines)]
        plan = made._jdf.queryExecution().optimizedPlan().toString()
        assert "l_tax" not in plan.split("Relation")[0] and (name == "li_qty" or "Join" not in plan)


def test_all_methods_size_segments_of_both_widths_in_one_pass(spark, monkeypatch):
    import numpy as np

    from seriespack.operators import baselines
    from seriespack.operators.options import preset

    monkeypatch.setattr(queries, "KERNEL", 1 << 16)
    rng, presets = np.random.default_rng(7), ("speed", "balanced", "ratio", "speed_huffman")
    v = np.cumsum(rng.integers(-3, 4, (1 << 16) + 77)) % 65536
    x = spark.createDataFrame([(t, int(u) >> 8, int(u)) for t, u in enumerate(v)], "t bigint, x8 bigint, x16 bigint").repartition(5).selectExpr("'s' series_id", "*")
    sizes = queries.all_methods(x, presets)
    plan = sizes._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("MapInArrow") == 1 and "InPandas" not in plan
    want = {}
    for w in (8, 16):
        parts = [p.astype(np.int64) for p in np.split(v >> (16 - w), [1 << 16])]
        raws = [p.astype(f"<u{w // 8}").tobytes() for p in parts]
        want |= {(m, w): sum(len(enc(p)) for p in parts) for m, (enc, _) in baselines.INTEGER.items()}
        want |= {(m, w): sum(len(baselines.general_encode(m, r)) for r in raws) for m in baselines.GENERAL}
        want |= {(m, w): sum(len(codec.pack_many([p.reshape(-1, 1)], preset(m, w))[0][0]) for p in parts) for m in presets}
    assert {(r.method, r.width_bits): r.enc_bytes for r in sizes.collect()} == want


def test_entropy_stages_share_a_forecast(spark, monkeypatch):
    import numpy as np

    from seriespack.operators.options import preset

    rng = np.random.default_rng(8)
    v = np.cumsum(rng.integers(-3, 4, 5003)) % 65536
    x = spark.createDataFrame([("s", t, int(u)) for t, u in enumerate(v)], "series_id string, t bigint, x bigint").repartition(3)
    monkeypatch.setattr(queries, "series", lambda *_: x)
    made = queries.q68_entropy_ablation(spark, "")
    assert "InPandas" not in made._jdf.queryExecution().optimizedPlan().toString()
    got, column = {r.stage: r.bytes for r in made.collect()}, v.reshape(-1, 1).astype(np.int64)
    kinds = {"none": preset("balanced", 16), "after": preset("ratio", 16), "before": preset("ratio", 16, entropy_order="before")}
    assert {k: got[k] for k in kinds} == {k: len(codec.pack_many([column], o)[0][0]) for k, o in kinds.items()}
    assert got["bound"] <= got["none"] and len(got) == 4
