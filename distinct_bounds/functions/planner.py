"""What a sketch costs and what it can hold."""

from __future__ import annotations

import math

from distinct_bounds.functions import bounds
from distinct_bounds.spec import SketchSpec


def overflow_chance(spec: SketchSpec, truth: float) -> float:
    """Bound on the chance that some hash word has no one in its first-one field."""
    return min(1.0, spec.c0 * truth * 2.0**-spec.first_one_bits)


def bit_budget(spec: SketchSpec, truth: float, spare: float = 10.0) -> int:
    """Bits a hash word needs so that the field overflows with a chance of 2**-spare at most."""
    return math.ceil(spec.r0 + spec.z0 + math.log2(max(1.0, truth) * spec.c0) + spare)


def check(spec: SketchSpec, truth: float, most: float = 1e-3) -> None:
    if overflow_chance(spec, truth) > most:
        raise ValueError(f"{spec.first_one_bits} first-one bits are too few for {truth:g} objects: {bit_budget(spec, truth)} bits a word are needed")


def memory_bits(spec: SketchSpec, truth: float) -> int:
    """Bits of all slots: the position needs log2 of its largest value, the refinement z0."""
    deepest = math.log2(max(2.0, truth)) + 10
    return spec.slots * (math.ceil(math.log2(deepest + 1)) + spec.z0)


def hashes_per_object(spec: SketchSpec) -> int:
    """Digests computed for each object: one that is split, or one a lane."""
    return 1 if spec.family == "sha2" else spec.c0


def slots_for_width(width: float, alpha: float) -> int:
    """Fewest slots whose shortest interval of level alpha is no wider than `width` on the log scale."""
    low, high = 1, 1
    while sum(bounds.log_shortest(alpha, high)[:2]) > width:
        low, high = high, high * 2
    while low < high:
        middle = (low + high) // 2
        low, high = (low, middle) if sum(bounds.log_shortest(alpha, middle)[:2]) <= width else (middle + 1, high)
    return low
