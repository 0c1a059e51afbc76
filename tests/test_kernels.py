"""The codec's kernels: worked examples, exact inverses, size identities."""

import numpy as np
import pytest

from seriespack.operators import baselines, huffman, models
from seriespack.operators import kernels as K
from seriespack.operators.codec import pack_many, unpack_many
from seriespack.operators.options import Options, preset


def kinds(rng, t, d, w):
    top = 1 << w
    yield rng.integers(0, top, (t, d))
    yield np.cumsum(rng.integers(-3, 4, (t, d)), 0) % top
    yield np.zeros((t, d), np.int64) + 7
    yield np.arange(t)[:, None] * rng.integers(0, 50, (1, d)) % top
    yield np.where(rng.random((t, d)) < 0.02, top - 1, 0)


CHANGES = [
    {"forecaster": "lag1"},
    {"forecaster": "fixed", "coef_num": -3},
    {"forecaster": "adaptive", "clamp": True},
    {"forecaster": "adaptive", "clamp": True, "update": "sample", "grad_stride": 1},
    {"forecaster": "adaptive", "clamp": True, "zero_rule": "case", "round_product": True},
    {"layout": "row", "group": 3},
    {"layout": "column", "group": 8, "rle": False},
    {"entropy": "huffman"},
    {"entropy": "huffman", "entropy_order": "before"},
    {"block": 16, "layout": "column"},
]


@pytest.mark.parametrize("w", [8, 16, 32])
@pytest.mark.parametrize("change", CHANGES, ids=str)
def test_round_trip(w, change):
    rng, o = np.random.default_rng(w), Options(width_bits=w, **change)
    for d in (1, 2, 5, 9):
        for t in (0, 1, 7, 8, 17, 200):
            segments = [x.astype(np.int64) for x in kinds(rng, t, d, w)]
            made = pack_many(segments, o)
            for x, y in zip(segments, unpack_many([(b, s, t, d) for b, s in made], o), strict=True):
                assert (x == y).all()


def test_zigzag_and_widths():
    e = np.arange(-128, 128)
    assert (K.unzigzag(K.zigzag(e)) == e).all()
    assert K.zigzag(np.array([0, -1, 1, -2])).tolist() == [0, 1, 2, 3]
    o = Options(width_bits=8)
    z = np.zeros((4, 8, 1), np.int64)
    z[:, 3, 0] = [16, 63, 64, 255]
    assert K.widths_of(z, o)[:, 0].tolist() == [5, 6, 8, 8]  # 7 is stored as 8


def test_isolated_spike_costs_a_bit():
    x = np.array([0, -1, 0, 0, 0, 0, 0, 0]).reshape(-1, 1)
    e = K.residuals(x, Options(width_bits=8))
    assert K.zigzag(e)[:4, 0].tolist() == [0, 1, 2, 0]


def test_lag1_zero_blocks_are_constant_data():
    x = np.full((80, 2), 9, np.int64)
    body, slots = K.pack(K.zigzag(K.residuals(x, Options())).reshape(-1, 8, 2), Options())
    assert slots == 2  # the first block, then a run


def test_coefficients_of_the_family():
    x = np.cumsum(np.arange(40)).reshape(-1, 1) % 65536
    smooth = K.residuals(x, Options(forecaster="fixed", coef_num=65536))
    assert (smooth[2:] == 1).all()
    lag = K.residuals(x, Options(forecaster="fixed", coef_num=0))
    assert (lag == K.residuals(x, Options())).all()


def test_worst_case_and_row_major_bound():
    assert round(models.worst_case_ratio(Options(width_bits=8), 1), 4) == 0.9412
    assert round(models.worst_case_ratio(Options(width_bits=16), 1), 4) == 0.9697
    x = np.cumsum(np.random.default_rng(0).integers(-1, 2, (800, 1)), 0) % 256
    (body, _), *_ = pack_many([x], Options(width_bits=8, layout="row", rle=False))
    assert len(body) >= 0.98 * x.size


def test_models():
    assert round(models.fill_seconds(10000, 9, 8, 20.0)) == 56
    assert models.encoder_memory_bytes(80, Options(width_bits=8, forecaster="adaptive")) == 960


def test_huffman():
    rng = np.random.default_rng(1)
    for n in (0, 1, 39, 40, 511, 512, 513, 4000):
        for p in (0.05, 0.5, 0.999):
            b = (rng.geometric(p, n) % 256).astype(np.uint8).tobytes()
            assert huffman.decode(huffman.encode(b)) == b
            assert len(huffman.encode(b)) <= len(b) + 6
    counts = 2 ** np.arange(20)
    lengths = huffman.code_lengths(counts)
    assert lengths.max() <= 11 and sum(2.0 ** -n for n in lengths) == 1
    counts = rng.integers(1, 1000, 60)
    lengths, p = huffman.code_lengths(counts), counts / counts.sum()
    entropy = -(p * np.log2(p)).sum()
    assert entropy <= (p * lengths).sum() < entropy + 1


@pytest.mark.parametrize("name", list(baselines.INTEGER))
def test_integer_baselines(name):
    enc, dec = baselines.INTEGER[name]
    rng = np.random.default_rng(2)
    for n in (0, 1, 127, 128, 129, 700):
        for v in (rng.integers(0, 256, n), np.zeros(n, int), np.where(rng.random(n) < 0.03, 60000, rng.integers(0, 8, n))):
            assert (dec(enc(v.astype(np.int64)), n) == v).all()


def test_presets_and_refusals():
    assert preset("ratio", 8).entropy == "huffman" and preset("speed", 8).forecaster == "lag1"
    with pytest.raises(ValueError):
        Options(width_bits=32, forecaster="adaptive")
    with pytest.raises(ValueError):
        Options(width_bits=12)


def test_what_the_package_offers_is_there():
    import seriespack

    assert all(callable(getattr(seriespack, name)) for name in seriespack.__all__)
    with pytest.raises(AttributeError):
        seriespack.nothing


@pytest.mark.parametrize("w", [8, 16])
@pytest.mark.parametrize("change", [{}, {"grad_stride": 1}, {"grad_stride": 3}, {"update": "sample", "grad_stride": 1}, {"rate_shift": 0}, {"rate_shift": 4}, {"clamp": True}, {"round_product": True}, {"zero_rule": "case"}, {"mean_rounding": "floor"}], ids=str)
def test_few_lanes_learn_as_many_do(w, change, monkeypatch):
    rng, o = np.random.default_rng(w), Options(width_bits=w, forecaster="adaptive", **change)
    for x in kinds(rng, 400, 3, w):
        few = K.residuals(x.astype(np.int64), o)
        with monkeypatch.context() as m:
            m.setattr(K, "FEW_LANES", 0)
            assert (K.residuals(x.astype(np.int64), o) == few).all()


@pytest.mark.parametrize("w", [8, 16])
@pytest.mark.parametrize("change", [{}, {"grad_stride": 1}, {"grad_stride": 3}, {"block": 16}, {"update": "sample", "grad_stride": 1}, {"update": "sample"}, {"rate_shift": 0}, {"rate_shift": 4}, {"clamp": True}, {"round_product": True}, {"zero_rule": "case"}, {"mean_rounding": "floor"}], ids=str)
def test_few_lanes_are_restored_as_many_are(w, change, monkeypatch):
    rng, o = np.random.default_rng(w), Options(width_bits=w, forecaster="adaptive", **change)
    for t in (0, 5, 8, 400, 403):
        e = rng.integers(-(1 << (w - 1)), 1 << (w - 1), (t, 3))
        for e in (e, e // 50, *(K.residuals(x.astype(np.int64), o) for x in kinds(rng, t // 8 * 8, 3, w))):
            few = K.reconstruct(e, o)
            with monkeypatch.context() as m:
                m.setattr(K, "FEW_LANES", 0)
                many = K.reconstruct(e, o)
            assert few.shape == many.shape and few.dtype == many.dtype and (few == many).all()


@pytest.mark.parametrize("w", [8, 16])
def test_a_whole_series_has_one_size_however_it_comes(w):
    from seriespack.operators.codec import _WholeSize

    rng, o = np.random.default_rng(w), preset("balanced", w)
    for column in (x[:, 0].astype(np.int64) for n in (0, 5, 8, 203, 3000) for x in kinds(rng, n, 1, w)):
        for piece in (1, 7, 64, 5000):
            size = _WholeSize(o)
            for i in range(0, len(column), piece):
                size.add(column[i : i + piece])
            assert size.close() == len(pack_many([column.reshape(-1, 1)], o)[0][0])


@pytest.mark.parametrize("name", list(baselines.INTEGER))
def test_sizes_are_those_of_the_encoders(name):
    rng = np.random.default_rng(4)
    for n in (0, 1, 127, 128, 129, 239, 240, 241, 3000):
        kinds_ = (rng.integers(0, 256, n), np.zeros(n, int), np.where(rng.random(n) < 0.03, 60000, rng.integers(0, 8, n)), rng.integers(0, 1 << 31, n) >> rng.integers(0, 32, n), (rng.random(n) < 0.01).astype(int))
        for v in kinds_:
            assert baselines.SIZES[name](v.astype(np.int64)) == len(baselines.INTEGER[name][0](v.astype(np.int64)))


@pytest.mark.parametrize("w", [8, 16])
@pytest.mark.parametrize("change", [{}, {"update": "sample", "grad_stride": 1}, {"clamp": True}, {"rle": False}, {"block": 16, "group": 3}, {"forecaster": "lag1"}], ids=str)
def test_sizes_are_those_of_packed_segments(w, change):
    from seriespack.operators.codec import size_many

    rng, o = np.random.default_rng(w), Options(width_bits=w, **{"forecaster": "adaptive"} | change)
    segments = [x.astype(np.int64) for n in (0, 1, 8, 9, 400, 401, 700, 1000) for lanes in (1, 3) for x in kinds(rng, n, lanes, w)]
    assert size_many(segments, o) == [len(body) for body, _ in pack_many(segments, o)]


def test_huffman_sizes_are_those_of_encoded_bodies():
    rng = np.random.default_rng(9)
    for n in (0, 1, 39, 40, 511, 512, 513, 5000):
        for v in (np.zeros(n), rng.integers(0, 2, n), rng.integers(0, 256, n), rng.geometric(0.3, n) % 256, np.where(rng.random(n) < 0.001, 200, 7)):
            body = v.astype(np.uint8).tobytes()
            assert huffman.encoded_size(body) == len(huffman.encode(body))
