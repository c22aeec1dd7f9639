"""Closed formulas: overheads, loads, false-positive rates, subfilter balance."""

from __future__ import annotations

import math

from fpfilter.operators.spec import SAFETY, FilterSpec, threshold

#: The best-case overhead factor's ``a * (1 + b / k)`` by filter type, and whether sizes are powers of two.
OVERHEAD = {
    "bloom": (1.443, 0.0, False),
    "classic": (1.05, 3.0, True),
    "windowed": (1.057, 2.0, False),
    "quotient": (1.053, 2.125, True),
    "vector_quotient": (1.075, 2.914, True),
}
#: Fixed value: the expected share of keys that a bin of 25 hands on.
PREFIX_SPARE = 1 / math.sqrt(50 * math.pi)
TYPES = (*OVERHEAD, "prefix")
#: Cache misses of an insertion and a lookup by type.
CACHE_MISSES = {
    "bloom": ("k", "k"),
    "classic": ("1 to walk cap", "2"),
    "windowed": ("1 to walk cap", "2"),
    "quotient": ("load dependent", "load dependent"),
    "vector_quotient": ("2", "2"),
    "prefix": ("1 or more", "1 or more"),
}


def overhead(kind: str, k: float, worst: bool = False) -> float:
    """Bits over n * k; in the worst case a power-of-two table is twice as large as needed."""
    if kind == "prefix":
        return (1 + PREFIX_SPARE) * (1 + 2 / k) + PREFIX_SPARE / k
    a, b, power = OVERHEAD[kind]
    return a * (1 + b / k) * (2 if worst and power else 1)


def table_overhead(layout: str, l: int, k: int) -> float:  # noqa: E741
    """Overhead of a table filled to SAFETY of its threshold."""
    return (k + 1 + math.log2(l)) / (k * SAFETY * threshold(layout, l))


def break_even() -> int:
    """The largest k at which the windowed table is smaller than the classic one: 1.06 (1 + 2/k) < 1.05 (1 + 3/k).

    In hundredths: 106 (k + 2) < 105 (k + 3), that is k < 105 * 3 - 106 * 2.
    """
    return 105 * 3 - 106 * 2 - 1


def index_bits_per_key(k: int) -> tuple[float, float]:
    """Bits a key of the windowed and the classic table."""
    return 1.06 * (k + 2), 1.05 * (k + 3)


def collision_values(spec: FilterSpec) -> float:
    """Distinct values that tell entries at one address apart, over the slots an address stands for."""
    values = (1 << spec.fp_bits) - 1
    return values if spec.layout == "window" else values / spec.l


def predicted_load(spec: FilterSpec, n: int) -> float:
    """Load after lookup-and-insert of n keys: each is skipped with the chance that its entry is there already."""
    full = n / spec.subs / spec.n_slots
    m = collision_values(spec)
    return m * -math.expm1(-full / m)


def predicted_fpr(spec: FilterSpec, load: float) -> float:
    """Chance that a key that was never inserted is found, at a load."""
    values = (1 << spec.fp_bits) - 1
    places = {"window": 1, "bucket": spec.l}[spec.layout] * (1 if spec.rule == "signed" else 2)
    return min(1.0, places * load / values)


def fpr_bound(first_share: float, places_log2: int, k: int) -> float:
    """The bound summed over both choice-bit values; it does not depend on their shares."""
    each = 2.0**places_log2 * 2.0 ** -(k + places_log2)
    return each * first_share + each * (1 - first_share)


def balance(n: int, subs: int) -> tuple[float, float]:
    """Mean and standard deviation of a subfilter's keys."""
    p = 1 / subs
    return n * p, math.sqrt(n * p * (1 - p))


def two_line_share(l: int, q: int, line_bits: int = 512) -> float:  # noqa: E741
    """How often a window of l slots spans two lines when q divides the line."""
    return (l - 1) * q / line_bits
