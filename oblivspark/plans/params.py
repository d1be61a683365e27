"""Public parameters of the routers, from the length alone, and bounds on how likely they fail."""

from __future__ import annotations

import math
from dataclasses import dataclass


def power_of_two(x: float) -> int:
    """The least power of two that is x or more."""
    return 1 << max(0, math.ceil(math.log2(max(x, 1))))


@dataclass(frozen=True)
class RouterParams:
    """n records; z slots a bin; beta bins; gamma ways a layer; words of a tag."""

    n: int
    z: int
    beta: int
    gamma: int
    tag_words: int

    @property
    def bits(self) -> int:
        return self.beta.bit_length() - 1

    @property
    def radix_bits(self) -> int:
        return max(1, self.gamma.bit_length() - 1)

    @property
    def layers(self) -> int:
        return -(-self.bits // self.radix_bits)

    @property
    def slots(self) -> int:
        return self.z * self.beta


def from_length(n: int, c: float = 1.0, gamma: int | None = None, eps: float | None = None) -> RouterParams:
    """Bins of about log2(n) squared slots, half of them real; ``eps`` gives the smaller bins of log2(n) to the 1 + eps / 2."""
    log = math.log2(max(n, 4))
    z = max(16, power_of_two(c * log ** (2 if eps is None else 1 + eps / 2)))
    beta = power_of_two(2 * max(n, 1) / z)
    if gamma is None:
        gamma = 1 << max(1, round(math.log2(log if eps is None else max(2.0, log ** (eps / 2)))))
    bits = max(16, math.ceil(log * math.log2(max(log, 2))))
    return RouterParams(n, z, beta, gamma, -(-bits // 64))


def log10_overflow(p: RouterParams) -> float:
    """Log10 of the union bound on any bin of any layer overflowing: Chernoff at twice the mean or more."""
    mean = p.n / p.beta
    if not mean:
        return -math.inf
    d = p.z / mean - 1
    tail = -mean * ((1 + d) * math.log(1 + d) - d) / math.log(10)
    return min(0.0, tail + math.log10(max(1, p.beta * p.layers)))


def log10_tag_collision(p: RouterParams) -> float:
    """Log10 of the bound on two records of one bin drawing one tag."""
    return min(0.0, math.log10(max(1, p.beta)) + 2 * math.log10(p.z) - 64 * p.tag_words * math.log10(2))


def pivot_bin_bound(n: int, c: float = 2.0) -> float:
    """The load of a region between neighbouring pivots that is exceeded with negligible probability: a constant times log2(n) cubed."""
    return c * math.log2(max(n, 4)) ** 3
