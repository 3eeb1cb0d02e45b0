"""What two sketches must agree on to be added: shape, field, hash and seed."""

from __future__ import annotations

import hashlib
import math
from dataclasses import dataclass

from ..functions import calibrate
from ..functions.algebra import FieldSpec


@dataclass(frozen=True)
class SketchPlan:
    """rows m, levels (cap of the level hash), field, seed; hash 'fast' (xxhash64) or 'portable' (md5, the same in
    other engines); offsets: rows thinned by a random share, so that the error has no periodic part."""

    rows: int
    field: FieldSpec
    levels: int = 48
    seed: int = 0
    hash: str = "fast"
    offsets: bool = False

    def __post_init__(self):
        if self.rows < 3:
            raise ValueError("a plan needs 3 rows at least")
        if not 1 <= self.levels <= 60:
            raise ValueError("levels must be from 1 to 60")
        if self.hash not in ("fast", "portable"):
            raise ValueError(f"no hash {self.hash!r}")

    @property
    def fingerprint(self) -> str:
        parts = f"{self.rows}/{self.field.p}^{self.field.k}/{self.levels}/{self.seed}/{self.hash}/{self.offsets}"
        return hashlib.sha256(parts.encode()).hexdigest()[:16]

    def row_offsets(self) -> list[float]:
        """One offset in [0, 1) for each row (zeros without offsets), drawn from the seed."""
        if not self.offsets:
            return [0.0] * self.rows
        digest = lambda i: hashlib.sha256(f"offset/{self.seed}/{i}".encode()).digest()
        return [int.from_bytes(digest(i)[:6], "big") / 2**48 for i in range(self.rows)]

    def thresholds(self) -> list[int]:
        """A row keeps an element if a 52-bit hash is below its threshold."""
        return [int(2.0**-o * 2**52) for o in self.row_offsets()]

    @property
    def memory_bits(self) -> int:
        """Bits of the full table: rows * levels * bits of an element."""
        return self.rows * self.levels * self.field.bits

    @property
    def factor(self) -> float:
        return calibrate.finite_factor(self.rows, self.field.order)

    @property
    def relative_error(self) -> float:
        return math.sqrt(calibrate.variance_ratio(self.rows, self.field.order))


def bit_table_bits(rows: int, levels: int) -> int:
    """Memory of the insert-only bit table of the same shape."""
    return rows * levels


def space_bound(scheme: str, eps: float, universe: float, linf: float = 1, mean: float = 1) -> float:
    """Bits, up to a constant, of counting integers by a prime drawn by ``scheme``."""
    base = math.log2(universe) / eps**2
    inner = {
        "small": math.log2(1 / eps) + math.log2(max(2.0, math.log2(max(2.0, linf)))),
        "above_max": math.log2(max(2.0, linf)),
        "above_mean": max(math.log2(max(1.0, mean)), math.log2(1 / eps)),
        "toggle": 1.0,
    }
    if scheme not in inner:
        raise ValueError(f"no scheme {scheme!r}")
    return base * inner[scheme]
