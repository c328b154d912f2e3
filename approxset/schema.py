"""Filter parameters and errors."""

from __future__ import annotations

import math
from dataclasses import dataclass, replace


class FilterFull(ValueError):
    """More items than the load limit allows."""


class FilterSpecMismatch(ValueError):
    """Filters whose fingerprints can't be combined."""


@dataclass(frozen=True)
class FilterSpec:
    """p fingerprint bits over `slots` slots (any number; a power of two splits the bits cleanly).

    quotient = fingerprint div width, remainder = fingerprint mod width, width = ceil(2^p / slots)."""

    p: int
    slots: int
    family: str = "portable"
    seed: int = 0
    variant: str = "three_bit"
    mode: str = "multiset"
    max_load: float = 0.75

    def __post_init__(self):
        if not 0 < self.p <= 60 or not 0 < self.slots <= 1 << self.p:
            raise ValueError(f"p={self.p}, slots={self.slots}")

    @property
    def width(self) -> int:
        if self.variant == "reserved":  # one stored value is kept to mean empty
            return (1 << self.r) - 1
        return -(-(1 << self.p) // self.slots)

    @property
    def r(self) -> int:
        return max(1, (-(-(1 << self.p) // self.slots) - 1).bit_length())

    @property
    def q(self) -> int:
        return (self.slots - 1).bit_length()

    @classmethod
    def for_items(cls, n: int, eps: float, load: float = 0.75, **more) -> FilterSpec:
        """The least power of two of slots that holds n items at the load, with a false-positive rate of at most eps."""
        q = max(1, math.ceil(math.log2(max(n, 1) / load)))
        r = max(1, math.ceil(math.log2(max(n, 1) / (1 << q) / eps)))
        return cls(p=q + r, slots=1 << q, max_load=load, **more)

    @classmethod
    def for_bytes(cls, size: int, eps: float, load: float = 0.75, bits: int = 3) -> FilterSpec:
        """As many slots as fit `size` bytes, power of two or not."""
        r = max(1, math.ceil(math.log2(load / eps)))
        slots = size * 8 // (r + bits)
        return cls(p=r + (slots - 1).bit_length(), slots=slots, max_load=load)

    def resized(self, by: int) -> FilterSpec:
        """One bit between quotient and remainder per step: the fingerprints stay, the slots double or halve."""
        return replace(self, slots=self.slots << by if by >= 0 else self.slots >> -by)

    def check(self, items: int, load: float | None = None) -> None:
        if items >= self.slots or items > (load or 1) * self.slots:
            raise FilterFull(f"{items} items in {self.slots} slots")

    def same_space(self, other: FilterSpec) -> None:
        if (self.p, self.family, self.seed) != (other.p, other.family, other.seed):
            raise FilterSpecMismatch(f"{self} and {other}")
