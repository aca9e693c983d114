"""What a sketch is made of, and the guard that only equal sketches are combined."""

from __future__ import annotations

import math
from dataclasses import dataclass, replace

FAMILIES, LAYOUTS, INITS = ("portable", "fast"), ("averaged", "full"), ("seeded", "none")


class SpecMismatch(ValueError):
    """Sketches of different specs were to be combined."""


@dataclass(frozen=True)
class SketchSpec:
    """k registers; ``portable`` hashes with md5 digits (52 bits, any engine can repeat it), ``fast``
    with xxhash64 (63 bits). ``averaged`` sends an item to one register, ``full`` to all. ``seeded``
    starts each register with its own draw (averaged only)."""

    k: int = 256
    seed: str = "s1"
    family: str = "portable"
    layout: str = "averaged"
    init: str = "seeded"

    def __post_init__(self):
        if self.k < 1:
            raise ValueError("k must be 1 or more")
        if self.family not in FAMILIES or self.layout not in LAYOUTS or self.init not in INITS:
            raise ValueError(f"unknown family, layout or init: {self}")
        if self.layout == "full" and self.init == "seeded":
            object.__setattr__(self, "init", "none")

    @property
    def bits(self) -> int:
        """Bits of the raw hash w that a register keeps the minimum of."""
        return 52 if self.family == "portable" else 63

    @property
    def spec_id(self) -> str:
        return f"{self.layout}-{self.family}-k{self.k}-{self.seed}-{self.init}"

    @property
    def factor(self) -> int:
        """Multiplier of the estimate: k where a register sees one k-th of the items."""
        return self.k if self.layout == "averaged" else 1

    @classmethod
    def for_error(cls, eps: float, constant: str = "order", **more) -> SketchSpec:
        """k for a relative error: eps**-2 (the order), or (pi/eps)**2 (the proved constant)."""
        return cls(k=registers_for(eps, constant), **more)

    def with_(self, **changes) -> SketchSpec:
        return replace(self, **changes)


def registers_for(eps: float, constant: str = "order") -> int:
    if not 0 < eps < 1:
        raise ValueError("eps must lie between 0 and 1")
    root = {"order": 1.0, "proved": math.pi}[constant] / eps
    return math.ceil(root * root - 1e-9)


def same(*specs: SketchSpec) -> SketchSpec:
    """The one spec of several sketches; raises SpecMismatch if they differ."""
    if len(set(specs)) != 1:
        raise SpecMismatch(" / ".join(s.spec_id for s in specs))
    return specs[0]
