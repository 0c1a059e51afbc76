"""NumPy kernels of the residual block codec; lanes (segment x column) advance in lock-step.

Samples are int64 arrays (time x lanes), arithmetic is modulo 2^w.  An encoder knows all differences
beforehand, so within a block only the coefficient is state; a decoder walks from sample to sample.
"""

from __future__ import annotations

import sys
import types

import numpy as np

from .options import Options


def wrap(v: np.ndarray, w: int) -> np.ndarray:
    half = 1 << (w - 1)
    return ((v + half) & ((1 << w) - 1)) - half


def zigzag(e: np.ndarray) -> np.ndarray:
    return (e << 1) ^ (e >> 63)


def unzigzag(z: np.ndarray) -> np.ndarray:
    return np.where(z & 1, -(z >> 1) - 1, z >> 1)


def bit_length(v: np.ndarray) -> np.ndarray:
    """Significant bits of numbers below 2^53."""
    return np.frexp(v.astype(np.float64))[1].astype(np.int64)


class Learner:
    """Coefficients of all lanes in fixed point, learnt from residual signs."""

    def __init__(self, lanes: int, o: Options):
        self.o, self.gain = o, np.zeros(lanes, np.int64)
        w = o.width_bits
        self.low, self.high = -(1 << (2 * w - 1)), (1 << (2 * w - 1)) - 1
        if o.clamp:
            self.low, self.high = -(1 << (w - 1)) << o.rate_shift, (1 << w) << o.rate_shift
        self.stride = np.arange(o.block) % o.grad_stride == o.grad_stride - 1
        self.sampled = int(self.stride.sum())

    def coef(self) -> np.ndarray:
        return self.gain >> self.o.rate_shift

    def estimate(self, coef: np.ndarray, step: np.ndarray) -> np.ndarray:
        product = coef * step
        if self.o.round_product:
            product = product + (1 << (self.o.width_bits - 1))
        return product >> self.o.width_bits

    def direction(self, residual: np.ndarray, step: np.ndarray) -> np.ndarray:
        sign = np.sign(residual)
        return (np.where(sign == 0, -1, sign) if self.o.zero_rule == "case" else sign) * step

    def add(self, gradient: np.ndarray) -> None:
        self.gain = np.minimum(np.maximum(self.gain + gradient, self.low), self.high)

    def mean(self, total: np.ndarray) -> np.ndarray:
        n = self.sampled
        if not n:
            return total * 0
        if n & (n - 1) == 0:  # an arithmetic shift rounds down; adding n - 1 to negative totals rounds toward zero
            rounded = total + ((total >> 63) & (n - 1)) if self.o.mean_rounding == "trunc" else total
            return rounded >> (n.bit_length() - 1)
        return np.where((total < 0) & (self.o.mean_rounding == "trunc"), -(-total // n), total // n)


#: Up to so many lanes, whole numbers of Python's own learn faster than arrays of a block's lanes.
FEW_LANES = 8


def coefficients(step: np.ndarray, last: np.ndarray, o: Options, gain: int = 0) -> tuple[np.ndarray, int]:
    """One lane's coefficients by sample, and the gain after its whole blocks; ``gain`` is that of what came before."""
    learner, w = Learner(1, o), o.width_bits
    low, high, shift, n = learner.low, learner.high, o.rate_shift, learner.sampled
    half, mask, rounding, trunc = 1 << (w - 1), (1 << w) - 1, (1 << (w - 1)) * o.round_product, o.mean_rounding == "trunc"
    at_zero, used = -(o.zero_rule == "case"), []
    if o.update == "sample":
        stride = (learner.stride.tolist() * (len(step) // o.block + 1))[: len(step)]
        for s, p, learns in zip(step.tolist(), last.tolist(), stride, strict=True):
            coef = gain >> shift
            used.append(coef)
            if learns and p:
                e = (s - ((coef * p + rounding) >> w) + half) & mask
                gain = min(max(gain + (p if e > half else -p if e < half else at_zero * p), low), high)
        return np.array(used, np.int64), gain
    whole = len(step) // o.block * o.block
    picked = [a[:whole].reshape(-1, o.block)[:, learner.stride].tolist() for a in (step, last)]
    for ss, ps in zip(*picked, strict=True):
        coef, total = gain >> shift, 0
        used.append(coef)
        for s, p in zip(ss, ps, strict=True):
            if p:
                e = (s - ((coef * p + rounding) >> w) + half) & mask
                total += p if e > half else -p if e < half else at_zero * p
        if total:
            gain += -(-total // n) if trunc and total < 0 else total // n
            gain = low if gain < low else high if gain > high else gain
    used.append(gain >> shift)
    return np.repeat(np.array(used, np.int64), o.block)[: len(step)], gain


def residuals(x: np.ndarray, o: Options) -> np.ndarray:
    """Residuals of samples (time x lanes); time is a multiple of the block for the adaptive forecaster."""
    w, lanes = o.width_bits, x.shape[1]
    step = wrap(np.diff(x, axis=0, prepend=np.zeros((1, lanes), np.int64)), w)
    if o.forecaster == "lag1":
        return step
    last = np.concatenate([np.zeros((1, lanes), np.int64), step])[: len(step)]
    if o.forecaster == "fixed":
        return wrap(step - (o.coef_num * last >> w), w)
    if lanes <= FEW_LANES and w <= 16:
        coef = np.stack([coefficients(step[:, j], last[:, j], o)[0] for j in range(lanes)], axis=1) if lanes else step
        return wrap(step - Learner(lanes, o).estimate(coef, last), w)
    learner, out = Learner(lanes, o), np.empty_like(step)
    if o.update == "sample":
        for t in range(len(step)):
            out[t] = wrap(step[t] - learner.estimate(learner.coef(), last[t]), w)
            if learner.stride[t % o.block]:
                learner.add(learner.direction(out[t], last[t]))
        return out
    for b in range(0, len(step), o.block):
        s, p = step[b : b + o.block], last[b : b + o.block]
        e = wrap(s - learner.estimate(learner.coef(), p), w)
        out[b : b + o.block] = e
        if len(e) == o.block:
            learner.add(learner.mean(learner.direction(e[learner.stride], p[learner.stride]).sum(0)))
    return out


def final_gain(x: np.ndarray, o: Options) -> np.ndarray:
    """The learner's state after all whole blocks, divided by the rate: coefficient times 2^w."""
    w, lanes = o.width_bits, x.shape[1]
    e = residuals(x, o)
    step = wrap(np.diff(x, axis=0, prepend=np.zeros((1, lanes), np.int64)), w)
    last = np.concatenate([np.zeros((1, lanes), np.int64), step[:-1]])
    learner = Learner(lanes, o)
    for b in range(0, len(x) - o.block + 1, o.block):
        k = learner.stride
        learner.add(learner.mean(learner.direction(e[b : b + o.block][k], last[b : b + o.block][k]).sum(0)))
    return learner.coef()


def differences(e: np.ndarray, o: Options) -> np.ndarray:
    """One lane's differences from the residuals that ``coefficients`` leaves."""
    learner, w = Learner(1, o), o.width_bits
    low, high, shift, n = learner.low, learner.high, o.rate_shift, learner.sampled
    half, mask, rounding, trunc = 1 << (w - 1), (1 << w) - 1, (1 << (w - 1)) * o.round_product, o.mean_rounding == "trunc"
    at_zero, each, stride = -(o.zero_rule == "case"), o.update == "sample", learner.stride.tolist()
    p = gain = coef = total = 0
    made, values = [], e.tolist()
    for start in range(0, len(values), o.block):
        block = values[start : start + o.block]
        for r, learns in zip(block, stride):
            last, p = p, ((((coef * p + rounding) >> w) + r + half) & mask) - half
            made.append(p)
            if learns:
                total += last if r > 0 else -last if r < 0 else at_zero * last
                if each:
                    gain, total = min(max(gain + total, low), high), 0
                    coef = gain >> shift
        if total and len(block) == o.block:
            gain += -(-total // n) if trunc and total < 0 else total // n
            gain, total = low if gain < low else high if gain > high else gain, 0
            coef = gain >> shift
    return np.array(made, np.int64)


def reconstruct(e: np.ndarray, o: Options) -> np.ndarray:
    """Samples modulo 2^w of residuals (time x lanes)."""
    w = o.width_bits
    mask = (1 << w) - 1
    if o.forecaster == "lag1":
        return np.cumsum(e, 0) & mask
    if o.forecaster == "fixed" and o.coef_num == 1 << w:
        return np.cumsum(np.cumsum(e, 0) & mask, 0) & mask
    if o.forecaster == "adaptive" and 0 < e.shape[1] <= FEW_LANES and w <= 16:
        return np.cumsum(np.stack([differences(lane, o) for lane in e.T], axis=1), 0) & mask
    lanes, out, half = e.shape[1], np.empty_like(e), 1 << (w - 1)
    learner, step = Learner(lanes, o), np.zeros(lanes, np.int64)
    coef = np.full(lanes, o.coef_num) if o.forecaster == "fixed" else learner.coef()
    rounding = half if o.round_product and o.forecaster == "adaptive" else 0
    shifted, now = e + half, np.empty(lanes, np.int64)
    for t in range(len(e)):
        np.multiply(coef, step, out=now)
        if rounding:
            now += rounding
        now >>= w
        now += shifted[t]
        now &= mask
        np.subtract(now, half, out=out[t])
        if o.forecaster == "adaptive":
            i = t % o.block
            if o.update == "sample":
                if learner.stride[i]:
                    learner.add(learner.direction(e[t], step))
                    coef = learner.coef()
            elif i == o.block - 1:
                at = np.flatnonzero(learner.stride) + t - i
                before = out[at - 1] if at[0] else np.concatenate([np.zeros((1, lanes), np.int64), out[at[1:] - 1]])
                learner.add(learner.mean(learner.direction(e[at], before).sum(0)))
                coef = learner.coef()
        step = out[t]
    return np.cumsum(out, 0) & mask


def widths_of(z: np.ndarray, o: Options) -> np.ndarray:
    """Stored widths (blocks x columns) of zigzagged residuals (blocks x block x columns)."""
    while z.shape[1] > 1 and z.shape[1] % 2 == 0:
        z = z[:, ::2] | z[:, 1::2]
    k = bit_length(z[:, 0] if z.shape[1] == 1 else np.bitwise_or.reduce(z, axis=1))
    return np.where(k >= o.width_bits - 1, o.width_bits, k)


def layout_of(o: Options, dims: int) -> str:
    return o.layout if o.layout != "auto" else "column" if dims * o.width_bits <= 32 else "row"


def payload_sizes(widths: np.ndarray, o: Options) -> np.ndarray:
    """Bytes of each block's payload."""
    if layout_of(o, widths.shape[-1]) == "column":
        return (-(-widths * o.block // 8)).sum(-1)
    return -(-widths.sum(-1) // 8) * o.block


def varint(n: int) -> bytes:
    out = bytearray()
    while n >= 128:
        out.append(n & 127 | 128)
        n >>= 7
    return bytes([*out, n])


def varint_sizes(n: np.ndarray) -> np.ndarray:
    return np.maximum(-(-bit_length(n) // 7), 1)


def to_slots(widths: np.ndarray, o: Options) -> tuple[np.ndarray, np.ndarray]:
    """First block of each slot, and for runs of zero blocks their length (0 for data)."""
    zero = ~widths.any(1)
    if not o.rle or not len(zero):
        return np.arange(len(zero)), np.zeros(len(zero), np.int64)
    starts = np.flatnonzero(~zero | ~np.concatenate([[False], zero[:-1]]))
    return starts, np.where(zero[starts], np.diff(starts, append=len(zero)), 0)


def stream_bytes(widths: np.ndarray, o: Options) -> int:
    """Bytes that ``pack`` makes of blocks of these stored widths (blocks x columns)."""
    first, run = to_slots(widths, o)
    if not len(first):
        return 0
    lengths, data = run[run > 0], first[run == 0]
    header = -(-np.bincount(np.arange(len(first)) // o.group) * widths.shape[1] * (o.width_bits.bit_length() - 1) // 8)
    return int(header.sum() + payload_sizes(widths[data], o).sum() + varint_sizes(lengths).sum())


def _bases(widths: np.ndarray, start: np.ndarray, o: Options) -> tuple[np.ndarray, np.ndarray]:
    """Bit place of each column's first value, and the distance to the next, for payloads that start at bit ``start``."""
    if layout_of(o, widths.shape[1]) == "column":
        size = -(-widths * o.block // 8) * 8
        return start[:, None] + np.cumsum(size, 1) - size, widths
    row = -(-widths.sum(1) // 8) * 8
    return start[:, None] + np.cumsum(widths, 1) - widths, np.broadcast_to(row[:, None], widths.shape)


def put_bits(values: np.ndarray, place: np.ndarray, width: np.ndarray, size: int) -> np.ndarray:
    """``size`` bytes that hold values of ``width`` bits from bit ``place`` on, least significant first; places ascend and no two values overlap."""
    out = np.zeros(size // 8 + 2, np.uint64)
    if not len(values):
        return out.view(np.uint8)[:size]
    values, word, shift = values.astype(np.uint64), place >> 6, (place & 63).astype(np.uint64)
    first = np.flatnonzero(np.diff(word, prepend=-1))
    out[word[first]] = np.bitwise_or.reduceat(values << shift, first)
    over = np.flatnonzero(shift.astype(np.int64) + width > 64)
    out[word[over] + 1] |= values[over] >> (np.uint64(64) - shift[over])
    return out.view(np.uint8)[:size]


def get_bits(data: bytes, place: np.ndarray, width: np.ndarray) -> np.ndarray:
    """Values of ``width`` bits from bit ``place`` on, least significant first."""
    words = np.frombuffer(data + bytes(16 - len(data) % 8), np.uint64)
    word, shift = place >> 6, (place & 63).astype(np.uint64)
    out = words[word] >> shift
    out |= (words[word + 1] << np.uint64(1)) << (np.uint64(63) - shift)
    return (out & ((np.uint64(1) << width.astype(np.uint64)) - np.uint64(1))).astype(np.int64)


def _places(widths: np.ndarray, start: np.ndarray, o: Options) -> tuple[np.ndarray, np.ndarray, bool]:
    """Bit place and width of every value of payloads that start at bit ``start``, in ascending order; and whether columns lead."""
    base, stride = _bases(widths, start, o)
    by_column = layout_of(o, widths.shape[1]) == "column"
    if by_column:
        place = base[:, :, None] + stride[:, :, None] * np.arange(o.block)
        width = np.broadcast_to(widths[:, :, None], place.shape)
    else:
        place = base[:, None, :] + stride[:, None, :] * np.arange(o.block)[:, None]
        width = np.broadcast_to(widths[:, None, :], place.shape)
    return place, width, by_column


def pack(z: np.ndarray, o: Options) -> tuple[bytes, int]:
    """Headers and payloads of all blocks (blocks x block x columns): the slot stream, and how many slots."""
    dims, h = z.shape[2], o.width_bits.bit_length() - 1
    widths = widths_of(z, o)
    first, run = to_slots(widths, o)
    n = len(first)
    if not n:
        return b"", 0
    runs = np.flatnonzero(run)
    counts = [varint(int(r)) for r in run[runs]]
    size = payload_sizes(widths[first], o)
    size[runs] = [len(c) for c in counts]
    group = np.arange(n) // o.group
    header = -(-np.bincount(group) * dims * h // 8)
    before, headers_done = np.cumsum(size) - size, np.cumsum(header)
    at = before + headers_done[group]
    group_at = before[np.arange(len(header)) * o.group] + headers_done - header
    total = int(size.sum() + header.sum())
    place = ((group_at[group] * 8 + (np.arange(n) % o.group) * dims * h)[:, None] + np.arange(dims) * h).reshape(-1)
    body = put_bits(np.minimum(widths[first], o.width_bits - 1).reshape(-1), place, np.full(len(place), h), total)
    data = run == 0
    blocks = first[data]
    place, width, by_column = _places(widths[blocks], at[data] * 8, o)
    values = z[blocks] if len(blocks) < len(z) else z
    body |= put_bits((values.transpose(0, 2, 1) if by_column else values).reshape(-1), place.reshape(-1), width.reshape(-1), total)
    for i, count in zip(runs.tolist(), counts, strict=True):
        body[at[i] : at[i] + len(count)] = np.frombuffer(count, np.uint8)
    return body.tobytes(), n


def _headers(dims: int, o: Options) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """``_header_tables``, remembered as long as the Python process lives and never sent along with a task."""
    known = sys.modules.setdefault("_seriespack_kernels", types.ModuleType("_seriespack_kernels")).__dict__
    key = (dims, o.width_bits, o.group, o.layout, o.block, o.rle)
    if key not in known:
        known[key] = _header_tables(dims, o)
    return known[key]


def _header_tables(dims: int, o: Options) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """For each header of a full group, where it has at most 16 bits: widths, payload sizes, and the group's size (-1 where it holds a run)."""
    h, top = o.width_bits.bit_length() - 1, o.width_bits - 1
    hb = -(-o.group * dims * h // 8)
    codes = (np.arange(1 << (8 * hb))[:, None] >> (np.arange(o.group * dims) * h)) & top
    wide = np.where(codes == top, o.width_bits, codes).reshape(-1, o.group, dims)
    size = payload_sizes(wide.reshape(-1, dims), o).reshape(-1, o.group)
    runs = (~wide.any(2)).any(1) & o.rle
    return wide, size, np.where(runs, -1, size.sum(1) + hb)


def _read_varint(body: bytes, at: int) -> tuple[int, int]:
    n = shift = 0
    while True:
        byte = body[at]
        n |= (byte & 127) << shift
        at, shift = at + 1, shift + 7
        if byte < 128:
            return n, at


def _group_slots(body: bytes, at: int, sizes: list[int], zero: list[bool]) -> tuple[list[int], list[int], int]:
    """Places and run lengths of a group's slots, whose payloads begin at ``at``, and where they end."""
    places, runs = [], []
    for size, is_run in zip(sizes, zero, strict=True):
        places.append(at)
        n = 0
        if is_run:
            n, at = _read_varint(body, at)
        else:
            at += size
        runs.append(n)
    return places, runs, at


def _parse_narrow(body: bytes, groups: int, dims: int, o: Options) -> tuple[np.ndarray, np.ndarray, np.ndarray, int]:
    """Slots of the first full groups: a table says where the next group begins, so only groups with runs are looked into."""
    h = o.width_bits.bit_length() - 1
    hb = -(-o.group * dims * h // 8)
    wide, size, step = _headers(dims, o)
    raw = np.frombuffer(body + bytes(2), np.uint8).astype(np.int64)
    header = raw[: len(body)] + (raw[1 : len(body) + 1] << 8 if hb == 2 else 0)
    jump = step[header]
    after = np.where(jump < 0, -1, np.arange(len(body)) + jump).tolist()
    starts, odd, at = [], [], 0
    for _ in range(groups):
        starts.append(at)
        following = after[at]
        if following < 0:
            sizes = size[header[at]]
            places, runs, following = _group_slots(body, at + hb, sizes.tolist(), (sizes == 0).tolist())
            odd.append((len(starts) - 1, places, runs))
        at = following
    starts = np.array(starts)
    seen = header[starts]
    places, runs = starts[:, None] + hb + np.cumsum(size[seen], 1) - size[seen], np.zeros((len(starts), o.group), np.int64)
    for i, where, lengths in odd:
        places[i], runs[i] = where, lengths
    return wide[seen].reshape(-1, dims), runs.reshape(-1), places.reshape(-1), at


def parse_slots(body: bytes, n_slots: int, dims: int, o: Options) -> tuple[np.ndarray, np.ndarray, np.ndarray, int]:
    """Stored widths, run lengths and payload places of all slots, and where the stream ends.

    Headers are met again and again, so what each says is remembered.
    """
    h, top = o.width_bits.bit_length() - 1, o.width_bits - 1
    known: dict[bytes, tuple] = {}
    widths, runs, places, at, left = [np.zeros((0, dims), np.int64)], [np.zeros(0, np.int64)], [np.zeros(0, np.int64)], 0, n_slots
    if o.group * dims * h <= 16 and left >= 32:
        wide, run, place, at = _parse_narrow(body, left // o.group, dims, o)
        widths, runs, places, left = [wide], [run], [place], left % o.group
    while left > 0:
        k = min(o.group, left)
        hb = -(-k * dims * h // 8)
        key = body[at : at + hb]
        if (found := known.get((key, k))) is None:
            bits = np.unpackbits(np.frombuffer(key, np.uint8), bitorder="little")[: k * dims * h].reshape(k, dims, h)
            codes = bits @ (1 << np.arange(h))
            wide = np.where(codes == top, o.width_bits, codes)
            found = known[key, k] = (wide, payload_sizes(wide, o).tolist(), (~wide.any(1) & o.rle).tolist())
        place, run, at = _group_slots(body, at + hb, found[1], found[2])
        widths.append(found[0])
        runs.append(run)
        places.append(place)
        left -= k
    return np.concatenate(widths), np.concatenate(runs).astype(np.int64), np.concatenate(places).astype(np.int64), at


def unpack(body: bytes, n_slots: int, dims: int, o: Options) -> tuple[np.ndarray, int]:
    """Zigzagged residuals (blocks x block x columns), and where the stream ends."""
    widths, runs, places, end = parse_slots(body, n_slots, dims, o)
    length = np.where(runs > 0, runs, 1)
    first = np.cumsum(length) - length
    z = np.zeros((int(length.sum()), o.block, dims), np.int64)
    data = np.flatnonzero(runs == 0)
    place, width, by_column = _places(widths[data], places[data] * 8, o)
    values = get_bits(body[:end], place.reshape(-1), width.reshape(-1)).reshape(place.shape)
    z[first[data]] = values.transpose(0, 2, 1) if by_column else values
    return z, end
