"""Closed forms: encoder memory, buffer latency, transmission power."""

from __future__ import annotations

from .options import Options


def encoder_memory_bytes(dims: int, o: Options) -> int:
    """A raw block and each column's state: previous sample and difference of w bits, gain of 2w."""
    w = o.width_bits
    return o.block * dims * w // 8 + (dims * 4 * w // 8 if o.forecaster == "adaptive" else dims * w // 8)


def fill_seconds(buffer_bytes: int, dims: int, width_bits: int, hertz: float) -> float:
    return buffer_bytes / (dims * (width_bits / 8) * hertz)


def power_milliwatts(ratio: float, radio_mw: float, cpu_uw: float) -> float:
    """Radio time shrinks by the ratio at best; compressing adds the processor's power."""
    return radio_mw / ratio + cpu_uw / 1000


def worst_case_ratio(o: Options, dims: int) -> float:
    """Ratio of incompressible blocks."""
    h = o.width_bits.bit_length() - 1
    raw = o.group * o.block * dims * o.width_bits / 8
    return raw / (raw + -(-o.group * dims * h // 8))
