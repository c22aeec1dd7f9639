"""What a filter is: variant, widths, table size, hash factors; and how large to make it."""

from __future__ import annotations

import json
import math
from dataclasses import asdict, dataclass, replace

from fpfilter.functions.hashing import multiplier

#: Asymptotic load thresholds with two choices, by layout and slots per bucket or window.
LOAD_THRESHOLD = {
    ("bucket", 1): 0.5,
    ("bucket", 2): 0.8970118682,
    ("bucket", 3): 0.9591542686,
    ("bucket", 4): 0.9803697743,
    ("window", 1): 0.5,
    ("window", 2): 0.9649949234,
    ("window", 3): 0.9944227538,
    ("window", 4): 0.9989515932,
}
#: How much of the threshold is used.
SAFETY = 0.98
MAX_WALK = 10_000


@dataclass(frozen=True)
class FilterSpec:
    """``rule`` is the partner rule: signed offset, xor of the hashed or raw fingerprint, or mirrored sum.

    ``value_bits`` is the width of a value beside each slot, for tables that count or map.
    """

    k: int
    l: int  # noqa: E741
    layout: str = "window"
    rule: str = "signed"
    subs: int = 1
    n_addr: int = 0
    seed: int = 1
    premix: bool = True
    max_walk: int = MAX_WALK
    mode: str = "lookup_insert"
    value_bits: int = 0

    @property
    def offset_bits(self) -> int:
        return (self.l - 1).bit_length() if self.layout == "window" else 0

    @property
    def choice_bits(self) -> int:
        return 1 if self.rule == "signed" else 0

    @property
    def fp_bits(self) -> int:
        """Bits that the choice and offset bits do not already pay back for the 2 * l places that are searched."""
        return self.k + 1 + (self.l - 1).bit_length() - self.choice_bits - self.offset_bits

    @property
    def slot_bits(self) -> int:
        return self.fp_bits + self.choice_bits + self.offset_bits

    @property
    def n_slots(self) -> int:
        return self.n_addr + self.l - 1 if self.layout == "window" else self.n_addr * self.l

    @property
    def name(self) -> str:
        tail = {"signed": "", "xor": "xor", "xor_raw": "xorraw", "mirror": "mirror"}[self.rule]
        return f"{self.layout[0]}2{self.l}{tail}"

    @property
    def kind(self) -> str:
        return "cuckoo"

    def factor(self, role: str, b: int) -> int:
        return multiplier(self.seed, role, b)

    def to_json(self) -> str:
        return json.dumps(asdict(self), sort_keys=True)

    @staticmethod
    def from_json(text: str) -> FilterSpec:
        return FilterSpec(**json.loads(text))


def threshold(layout: str, slots: int) -> float:
    """The load threshold; windows and buckets of more than 4 slots are taken as full."""
    return LOAD_THRESHOLD.get((layout, slots), 1.0)


def sized(spec: FilterSpec, n: int, load: float | None = None, z: float = 4.0) -> FilterSpec:
    """``spec`` with addresses for ``n`` keys at ``load`` (default: SAFETY of the threshold).

    A subfilter gets room for its mean number of keys and ``z`` standard deviations. The xor rules need a power of
    two; they keep the classical 1.05 slots a key unless a load is given.
    """
    if load is None:
        load = 1 / 1.05 if spec.rule.startswith("xor") else SAFETY * threshold(spec.layout, spec.l)
    mean = n / spec.subs
    keys = mean + z * math.sqrt(max(0.0, mean * (1 - 1 / spec.subs)))
    slots = max(spec.l + 1, math.ceil(keys / load))
    if spec.layout == "window":
        return replace(spec, n_addr=slots - spec.l + 1)
    addresses = max(2, -(-slots // spec.l))
    if spec.rule.startswith("xor"):
        addresses = 1 << (addresses - 1).bit_length()
    return replace(spec, n_addr=addresses)


def grown(spec: FilterSpec, factor: float = 1.02) -> FilterSpec:
    """A larger table for the next attempt; the seed stays, as it also routes keys to subfilters."""
    n = spec.n_addr * 2 if spec.rule.startswith("xor") else max(spec.n_addr + 1, math.ceil(spec.n_addr * factor))
    return replace(spec, n_addr=n)


def variant(name: str, k: int, **more: object) -> FilterSpec:
    """A specification by its short name: ``w22 w24 b22 b24 w21 b21 b24xor b24xorraw b22mirror ...``."""
    layout = {"w": "window", "b": "bucket"}[name[0]]
    rule = {"": "signed", "xor": "xor", "xorraw": "xor_raw", "mirror": "mirror"}[name[3:]]
    return FilterSpec(k=k, l=int(name[2]), layout=layout, rule=rule, **more)


#: The four that experiments compare, the smallest first.
VARIANTS = ("w22", "w24", "b22", "b24")
ALL_VARIANTS = (*VARIANTS, "w21", "b21", "b24xor", "b24xorraw", "b22mirror", "b24mirror")
