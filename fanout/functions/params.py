"""Parameters of the recorder grid."""

from __future__ import annotations

from dataclasses import dataclass, replace
from math import ceil, exp, log2

ADDRESS_BITS, MAX_AGE = 32, 65_535


@dataclass(frozen=True)
class GridParams:
    """m recorders a sketch, r rows of 2^w columns, d bits between the pieces of neighbouring rows, threshold theta, span k.

    literal_shift shifts row i by i*d, so that the lowest d bits are in no piece and have to be searched.
    root_check compares the hash of a rebuilt address with its chain, pad_check wants no bits above the address.
    """

    m: int = 2048
    w: int = 14
    r: int = 5
    d: int = 6
    theta: int = 1024
    k: int = 1
    literal_shift: bool = False
    root_check: bool = True
    pad_check: bool = True

    def shift(self, row: int) -> int:
        return (row if self.literal_shift else row - 1) * self.d

    @property
    def mask(self) -> int:
        return (1 << self.w) - 1

    @property
    def overlap_mask(self) -> int:
        return (1 << (self.w - self.d)) - 1

    @property
    def cutoff(self) -> float:
        return hot_cutoff(self.m, self.theta)

    def validate(self) -> GridParams:
        if not 0 < self.d < self.w:
            raise ValueError("0 < d < w is needed")
        if self.shift(self.r - 1) + self.w < ADDRESS_BITS:
            raise ValueError("the pieces do not cover the address")
        if self.r < 3 or self.m < 1 or self.theta < 1:
            raise ValueError("r >= 3, m >= 1 and theta >= 1 are needed")
        if not 0 < self.k < MAX_AGE:
            raise ValueError("0 < k < 65,535 is needed")
        return self

    def with_(self, **change) -> GridParams:
        return replace(self, **change).validate()


def hot_cutoff(m: int, theta: float) -> float:
    """Touched recorders that theta counterparts are expected to leave."""
    return m * (1 - exp(-theta / m))


def linear_stderr(n: float, m: int) -> float:
    """Relative standard error of the bitmap estimate of n counterparts on m bits."""
    t = n / m
    return (m * (exp(t) - t - 1)) ** 0.5 / n


def advise(expected_hot: int, theta: int, max_error: float = 0.05, shards: int = 1) -> GridParams:
    """The smallest grid whose chains do not multiply and whose estimate keeps to max_error.

    A step multiplies chains by (hot cells a row) / 2^(w-d), so 2^(w-d) is put above the hot cells of a shard.
    """
    m = 64
    while linear_stderr(theta, m) > max_error and m < 1 << 20:
        m *= 2
    spare = max(2, ceil(log2(max(2, expected_hot / shards))) + 1)
    best = None
    for w in range(spare + 1, 25):
        d = w - spare
        r = max(3, ceil((ADDRESS_BITS - w) / d) + 2)
        cost = r << w
        if best is None or cost < best[0]:
            best = (cost, w, d, r)
    _, w, d, r = best
    return GridParams(m=m, w=w, r=r, d=d, theta=theta).validate()


def max_window_hours(slot_seconds: float) -> float:
    """The longest window in hours that 16-bit ages allow."""
    return (MAX_AGE - 1) * slot_seconds / 3600
