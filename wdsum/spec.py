"""What a sketch is made with. Sketches of different specs never merge."""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class SketchSpec:
    """m registers of b bits (None: not truncated), hashed with a seed.

    ``hash`` is "fast" (xxhash64) or "portable" (md5, which other engines have
    too). ``on_bad_weight``: what null, NaN and weights of 0 or less do, "drop" or
    "error". ``on_conflict``: the weight of an element that comes with several.
    """

    m: int = 256
    b: int | None = 8
    seed: int = 0
    hash: str = "fast"
    on_bad_weight: str = "drop"
    on_conflict: str = "max"

    def __post_init__(self):
        if self.m < 1:
            raise ValueError("m is 1 at least")
        if self.b is not None and not 2 <= self.b <= 16:
            raise ValueError("b is from 2 to 16, or None")
        if self.hash not in ("fast", "portable") or self.on_bad_weight not in ("drop", "error") or self.on_conflict not in ("error", "max", "min", "first"):
            raise ValueError(f"unknown option in {self}")

    @property
    def low(self) -> int:
        """Smallest register value; untruncated registers start below any double's bucket."""
        return -(1 << (self.b - 1)) + 1 if self.b else -1100

    @property
    def high(self) -> int:
        return (1 << (self.b - 1)) - 1 if self.b else 1100
