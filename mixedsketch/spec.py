"""Parameters of a sketch and the constants of its hash family."""

from __future__ import annotations

import math
from dataclasses import dataclass, replace

PRIME = 2**31 - 1


def _power(base: int, e: int) -> int:
    return pow(base, e, PRIME)


@dataclass(frozen=True)
class SketchSpec:
    """P parts of an H x K counter matrix, C slots a part, hand-off buffers of C keys and B counts, weight w of the moving average.

    H is the number of rows (hash functions) and K the number of columns.
    """

    P: int = 4
    H: int = 4
    K: int = 256
    C: int = 16
    B: int | None = 1000
    w: float = 0.8
    hash_family: str = "md5"
    producer: str = "round_robin"
    flush_lag: int = 0
    self_buffer: bool = True

    def __post_init__(self):
        if min(self.P, self.H, self.K) < 1 or self.C < 0 or not 0 < self.w <= 1:
            raise ValueError("P, H, K must be positive, C non-negative and 0 < w <= 1")
        if self.hash_family not in ("md5", "xxhash64") or self.producer not in ("round_robin", "contiguous"):
            raise ValueError("unknown hash family or producer assignment")

    @staticmethod
    def from_error(eps: float, delta: float, **more) -> SketchSpec:
        """Point queries overestimate by at most eps * F1 with probability 1 - delta: K = ceil(e/eps) columns, H = ceil(ln(1/delta)) rows."""
        return SketchSpec(H=max(1, math.ceil(math.log(1 / delta))), K=math.ceil(math.e / eps), **more)

    def row(self, j: int) -> tuple[int, int]:
        """(a, b) of row hash j."""
        return _power(48271, j + 1), _power(69621, j + 1)

    @property
    def owner(self) -> tuple[int, int]:
        return _power(48271, 101), _power(69621, 101)

    def sign(self, j: int) -> list[int]:
        """Four coefficients, highest degree first, of the 4-wise independent sign of row j."""
        return [_power(40692, 4 * j + t + 1) for t in range(4)]

    def but(self, **changes) -> SketchSpec:
        return replace(self, **changes)

    @property
    def key(self) -> str:
        """Identifies sketches that may be merged."""
        return f"P{self.P}-H{self.H}-K{self.K}-C{self.C}-{self.hash_family}"


#: The spec of the registered queries: few columns on purpose, so that keys collide.
TEST = SketchSpec(P=4, H=4, K=256, C=16, B=64)
#: The sizes of the published evaluation.
PAPER = SketchSpec(P=16, H=8, K=1024, C=16, B=1000)


def cm_plus_bounds(H: int, K: int, z: float) -> tuple[float, float]:
    """(relative error up to a constant, failure probability) of the squared-counter estimate for skew z > 1."""
    return K ** (-(1 + z) / 2), (3 / 4) ** H


SLOT_BYTES, BUFFER_KEY_BYTES, BUFFER_HEAD_BYTES, COUNTER_BYTES = 16, 8, 8, 4


def fit_width(spec: SketchSpec, layout: str = "composite") -> int:
    """Columns left when slots and buffers are paid from the budget of 4 * H * K bytes a part.

    ``layout``: plain (no slots), slots, or composite (slots and P buffers a part).
    """
    budget = COUNTER_BYTES * spec.H * spec.K
    slots = spec.C * SLOT_BYTES if layout in ("slots", "composite") else 0
    buffers = spec.P * (spec.C * BUFFER_KEY_BYTES + BUFFER_HEAD_BYTES) if layout == "composite" else 0
    return max(0, (budget - slots - buffers) // (COUNTER_BYTES * spec.H))
