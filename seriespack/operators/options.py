"""What a segment's bytes depend on."""

from __future__ import annotations

from dataclasses import dataclass, fields, replace


@dataclass(frozen=True)
class Options:
    """Options of the residual block codec; all that change the bytes travel with each segment."""

    width_bits: int = 16
    forecaster: str = "lag1"  # lag1, fixed, adaptive
    entropy: str = "none"  # none, huffman
    block: int = 8
    group: int = 2
    layout: str = "auto"
    signed: bool = False
    coef_num: int = 0  # fixed: coefficient times 2^w
    rate_shift: int = 1
    update: str = "block"  # block, sample
    grad_stride: int = 2
    zero_rule: str = "sign"  # sign, case
    mean_rounding: str = "trunc"  # trunc, floor
    clamp: bool = False
    round_product: bool = False
    rle: bool = True
    entropy_order: str = "after"  # after, before

    def __post_init__(self):
        if self.width_bits not in (8, 16, 32):
            raise ValueError("samples have 8, 16 or 32 bits")
        if self.width_bits == 32 and self.forecaster == "adaptive" and not self.clamp:
            raise ValueError("32-bit samples need a clamped coefficient to stay within 64 bits")
        for name, known in (("forecaster", ("lag1", "fixed", "adaptive")), ("entropy", ("none", "huffman")), ("update", ("block", "sample")), ("zero_rule", ("sign", "case")), ("mean_rounding", ("trunc", "floor")), ("layout", ("auto", "row", "column")), ("entropy_order", ("after", "before"))):
            if getattr(self, name) not in known:
                raise ValueError(f"{name} is one of {known}")

    def as_dict(self) -> dict:
        return {f.name: getattr(self, f.name) for f in fields(self)}


#: The three settings that are evaluated, and the fourth that completes the square.
PRESETS = {
    "ratio": {"forecaster": "adaptive", "entropy": "huffman"},
    "balanced": {"forecaster": "adaptive", "entropy": "none"},
    "speed": {"forecaster": "lag1", "entropy": "none"},
    "speed_huffman": {"forecaster": "lag1", "entropy": "huffman"},
}


def preset(name: str, width_bits: int, **changes) -> Options:
    return replace(Options(width_bits=width_bits, **PRESETS[name]), **changes)
