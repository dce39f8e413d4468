"""Kinds of filters by their bits: a constant times n * log2(1 / rate), or a formula of their own."""

from __future__ import annotations

import math

from ..functions.formulas import LOG2E

#: bits for each key are CONSTANT * log2(1 / rate)
CONSTANTS = {"ideal": 1.0, "standard": LOG2E, "xor": 1.23}


def bits_per_key(kind: str, rate: float) -> float:
    """Bits that a kind takes for each key at a rate. Cuckoo tables (semi-sorted, 95 % full), morton and vacuum
    filters add a fixed number of bits to the logarithm, so they are no pure multiple of it."""
    want = math.log2(1 / rate)
    if kind in CONSTANTS:
        return CONSTANTS[kind] * want
    added = {"cuckoo": 2.0, "morton": 2.5, "vacuum": 2.0}[kind]
    return (want + added) / 0.95
