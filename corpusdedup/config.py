"""Parameters of a deduplication run."""

from __future__ import annotations

import math
from dataclasses import dataclass, replace
from functools import cached_property

FAMILIES = ("affine", "multibase", "murmur3", "sha1", "xxhash64")


def portable_stream(seed: int):
    """31-bit numbers of a linear congruential generator, the same in every language and version."""
    x = seed & (2**64 - 1)
    while True:
        x = (6364136223846793005 * x + 1442695040888963407) & (2**64 - 1)
        yield x >> 33


@dataclass(frozen=True)
class DedupConfig:
    """Defaults are the published settings; see the README for what each stands for."""

    k: int = 5
    unit: str = "char"
    n_hashes: int = 128
    bands: int = 16
    rows: int = 8
    theta: float = 0.8
    strict: bool = False
    p: int = 4_294_967
    q: int = 1_114_113
    family: str = "affine"
    seed: int = 42
    k_mult: float = 4.0
    num_buckets: int | None = None
    min_chars: int = 200
    alpha: float = 0.2
    beta: float = 0.5
    d_max: int = 2048
    buckets_per_pass: int | None = None
    oversize: str = "block_pairs"
    keep: str = "min_id"

    def __post_init__(self) -> None:
        if self.bands * self.rows != self.n_hashes:
            raise ValueError(f"{self.bands} bands of {self.rows} rows don't make {self.n_hashes} hashes")
        if self.family not in FAMILIES:
            raise ValueError(f"no such hash family: {self.family}")
        if self.unit not in ("char", "word"):
            raise ValueError(f"no such shingle unit: {self.unit}")
        if not 0 < self.q < self.p or self.q <= 0x10FFFF:
            raise ValueError("q must exceed every code point and be less than p")
        if self.p >= 2**31:
            raise ValueError("p must fit 31 bits, so that a * h + b fits 63")

    def but(self, **changes) -> DedupConfig:
        return replace(self, **changes)

    @cached_property
    def constants(self) -> tuple[list[int], list[int]]:
        """(a_i, b_i) of the remixing h -> (a_i h + b_i) mod p."""
        s = portable_stream(self.seed)
        a = [1 + next(s) % (self.p - 1) for _ in range(self.n_hashes)]
        b = [next(s) % self.p for _ in range(self.n_hashes)]
        return a, b

    @cached_property
    def bases(self) -> list[int]:
        """One base for each function of the multibase family."""
        s = portable_stream(self.seed + 1)
        return [0x110000 + next(s) % (self.p - 0x110000) for _ in range(self.n_hashes)]

    @property
    def min_matches(self) -> int:
        """Matching signature entries that make a pair: at least theta * H, or more than that if strict."""
        x = round(self.theta * self.n_hashes, 9)
        return math.floor(x) + 1 if self.strict else math.ceil(x)
