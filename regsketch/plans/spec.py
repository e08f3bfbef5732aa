"""Parameters of a sketch."""

from __future__ import annotations

from dataclasses import dataclass

HASHES = ("xxhash64", "md5_64")


@dataclass(frozen=True)
class SketchSpec:
    """2**p registers with values 0 to q+1, filled from 64-bit words of one hash function and seed.

    Sketches can be merged only if their specs are equal; ``reduced`` specs can be reached from finer ones.
    """

    p: int = 12
    q: int = 20
    algo: str = "xxhash64"
    seed: int = 0

    def __post_init__(self) -> None:
        if self.p < 0 or self.q < 0 or self.p + self.q > 64 or self.p > 26:
            raise ValueError(f"no sketch with p={self.p}, q={self.q}: p may be 0 to 26, and p + q 64 at most")
        if self.algo not in HASHES:
            raise ValueError(f"unknown hash {self.algo!r}; there are {', '.join(HASHES)}")

    @property
    def m(self) -> int:
        return 1 << self.p

    @property
    def bits_per_register(self) -> int:
        return max(1, (self.q + 1).bit_length())

    def reduced(self, p: int, q: int) -> SketchSpec:
        """The spec of a coarser sketch."""
        if p > self.p or p + q > self.p + self.q:
            raise ValueError(f"({self.p},{self.q}) cannot become ({p},{q})")
        return SketchSpec(p, q, self.algo, self.seed)

    def common(self, other: SketchSpec) -> SketchSpec:
        """The finest spec that both can be reduced to."""
        if (self.algo, self.seed) != (other.algo, other.seed):
            raise ValueError("sketches of different hash functions have nothing in common")
        p = min(self.p, other.p)
        return SketchSpec(p, min(self.p + self.q, other.p + other.q) - p, self.algo, self.seed)
