"""Privacy parameters and failure probabilities; all depend on declared values only, never on the data."""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass

from .hashing import SPACE


@dataclass(frozen=True)
class CustomSketch:
    """A further member of the class: a commutative, idempotent aggregate of values per slot.

    ``slot`` and ``val`` take (hash column, k); ``merge`` is the aggregate over ``val``; ``estimate`` and ``pi`` take k
    and aggregate over (slot, val), where slots without items have no row; ``bits`` bounds the size and, unless
    ``k_max`` says better, the number of influential items too.
    """

    slot: Callable
    val: Callable
    merge: Callable
    estimate: Callable
    pi: Callable
    bits: Callable[[int], int]
    k_max: Callable[[int], int] | None = None
    rel_std_error: Callable[[int], float] | None = None


CUSTOM: dict[str, CustomSketch] = {}
KINDS = ("fm", "linear", "bottomk", "adaptive", "hll")


def register_sketch(kind: str, sketch: CustomSketch) -> None:
    """Make ``SketchSpec(kind, k)`` usable in every build, merge and release."""
    if kind in KINDS:
        raise ValueError(f"{kind} is a sketch of the library")
    CUSTOM[kind] = sketch


def k_max_from_bits(bits: int) -> int:
    """Influential items of any sketch of the class: no more than its state has bits."""
    return bits


@dataclass(frozen=True)
class SketchSpec:
    """kind: fm, linear, bottomk, adaptive, hll or a registered one; k: slots or kept hashes.

    rate (linear only): share of the items that the sketch takes in, which widens its range.
    """

    kind: str
    k: int
    bitmap_len: int = 32
    rate: float = 1.0

    def __post_init__(self):
        if self.kind not in KINDS and self.kind not in CUSTOM:
            raise ValueError(f"unknown sketch {self.kind}")
        if self.k < 2 or self.kind in ("hll", "fm") and self.k & (self.k - 1):
            raise ValueError("k must be 2 or more, and a power of two for hll and fm")
        if not 0 < self.rate <= 1 or self.rate < 1 and self.kind != "linear":
            raise ValueError("rate is above 0 and up to 1, and below 1 for linear counting only")

    @property
    def k_max(self) -> int:
        """Most items whose removal alone can alter the state."""
        if own := CUSTOM.get(self.kind):
            return own.k_max(self.k) if own.k_max else k_max_from_bits(own.bits(self.k))
        return self.k * self.bitmap_len if self.kind == "fm" else self.k

    @property
    def size_bits(self) -> int:
        if own := CUSTOM.get(self.kind):
            return own.bits(self.k)
        return {"fm": self.k * self.bitmap_len, "linear": self.k, "bottomk": 64 * self.k, "adaptive": 64 * self.k, "hll": 5 * self.k}[self.kind]

    def rel_std_error(self, n: float) -> float:
        k = self.k
        if own := CUSTOM.get(self.kind):
            if own.rel_std_error is None:
                raise ValueError(f"no standard error is known for {self.kind}")
            return own.rel_std_error(k)
        if self.kind == "linear" and self.rate < 1:  # of the thinned items, and of the thinning
            return math.sqrt((k * (math.exp(n * self.rate / k) - n * self.rate / k - 1)) / self.rate**2 + n * (1 - self.rate) / self.rate) / n
        if self.kind == "linear" and n >= k:
            return math.sqrt(k * (math.exp(n / k) - n / k - 1)) / n
        return {"fm": 0.649, "linear": 1.0, "bottomk": 1.0, "adaptive": 1.2, "hll": 1.04}[self.kind] / math.sqrt(k)


@dataclass(frozen=True)
class Budget:
    eps: float
    delta: float = 0.0
    n_floor: int | None = None  # a public lower bound on the number of distinct items
    max_groups_per_unit: int = 1  # a public upper bound on the groups that one item can be in

    def __post_init__(self):
        if not self.eps > 0:
            raise ValueError("eps must be positive")
        if self.max_groups_per_unit < 1:
            raise ValueError("an item is in one group at least")

    @property
    def total_eps(self) -> float:
        """Of all groups together, by composition; each group has a hash function of its own."""
        return self.eps * self.max_groups_per_unit


def pi0(eps: float) -> float:
    """Bound on the chance that a fresh item alters the state."""
    return -math.expm1(-eps)


def min_cardinality(k_max: int, eps: float) -> float:
    return k_max / pi0(eps)


def threshold(eps: float) -> int:
    """A thinning hash passes below this; strictly less than pi0 of the hash space."""
    return math.ceil(pi0(eps) * SPACE) - 1


def epsilon_for(n: float, k_max: int, sup_pi: float) -> float:
    if n <= k_max or sup_pi >= 1:
        return math.inf
    return max(-math.log1p(-sup_pi), -math.log1p(-k_max / n))


def coupon_delta(v: float, q: float, n: float) -> float:
    return min(1.0, v * (1 - q) ** n)


def prior_floor(k: int, eps: float, factor: float = 8.0) -> float:
    """Least number of items under the earlier, looser analysis of the register sketch."""
    return factor * min_cardinality(k, eps)


def log_binom_cdf(m: int, n: int, q: float) -> float:
    """ln P(Bin(n, q) <= m)."""
    if m >= n:
        return 0.0
    if m < 0:
        return -math.inf
    term = lambda i: math.lgamma(n + 1) - math.lgamma(i + 1) - math.lgamma(n - i + 1) + i * math.log(q) + (n - i) * math.log1p(-q)
    logs = [term(i) for i in range(m + 1)]
    top = max(logs)
    return min(0.0, top + math.log(sum(math.exp(x - top) for x in logs)))


def linear_floor(k: int, eps: float, rate: float = 1.0) -> tuple[int, float]:
    """(slots that must be filled for a state not to violate, items that fill so many on average)."""
    b0 = max(0, math.ceil(k * (1 - pi0(eps) / rate)))
    return b0, sum(k / (rate * (k - i)) for i in range(b0))


def ln_delta_bound(spec: SketchSpec, n: float, eps: float) -> float:
    """ln of a closed bound on the failure probability of an unmodified sketch of n items; 0 where it says nothing.

    linear: the published form with the sound sign of its last factor; hash lists: relative entropy.
    """
    q, k = pi0(eps), spec.k
    if n <= min_cardinality(spec.k_max, eps):
        return 0.0
    if spec.kind == "hll":
        return min(0.0, math.log(k) - q * n / k)
    if spec.kind == "fm":
        v = math.ceil(-math.log2(q))
        return min(0.0, math.log(k * v) - 2.0**-v * n / k)
    if spec.kind == "linear":
        if spec.rate < q:
            return -math.inf
        b0, mu0 = linear_floor(k, eps, spec.rate)
        return min(0.0, math.log(mu0 / n) - b0 / k / mu0 * n + b0 / k) if n > mu0 else 0.0
    x = k / n
    return -n * (x * math.log(x / q) + (1 - x) * math.log((1 - x) / (1 - q)))


def occupancy_cdf(k: int, n: int, b: int, rate: float = 1.0) -> float:
    """P(fewer than b of k slots are filled by n items, each kept with ``rate``)."""
    import numpy as np

    stay = 1 - rate * (1 - np.arange(b + 1) / k)
    p = np.zeros(b + 1)
    p[0] = 1.0
    for _ in range(n):
        p = p * stay + np.append(0.0, (p * (1 - stay))[:-1])
        if p[:b].max(initial=0.0) < 1e-290:  # more items only lessen it
            break
    return min(1.0, float(p[:b].sum()))


def delta(spec: SketchSpec, n: int, eps: float, method: str = "exact") -> float:
    """Probability that an unmodified sketch of n items violates the bound.

    ``exact`` for linear, bottomk and adaptive is the true probability; fm and hll have the coupon bound only.
    ``printed`` is the published form of the hash-list bound, refused where it is not sound (eps > ln 2).
    """
    q, k = pi0(eps), spec.k
    if spec.kind in CUSTOM:
        raise ValueError(f"no failure probability is known for {spec.kind}: use a pure release")
    if n <= min_cardinality(spec.k_max, eps):
        return 1.0
    if spec.kind == "hll":
        return min(1.0, k * math.exp(-q * n / k))
    if spec.kind == "fm":
        v = math.ceil(-math.log2(q))
        return min(1.0, k * v * math.exp(-(2.0**-v) * n / k))
    if spec.kind == "linear":
        if spec.rate < q:  # its own thinning keeps every state below the bound
            return 0.0
        return occupancy_cdf(k, n, linear_floor(k, eps, spec.rate)[0], spec.rate)
    if method == "printed":
        if eps > math.log(2) + 1e-12:
            raise ValueError("the printed bound is not sound for eps > ln 2")
        a = (q - k / n) ** 2 / (2 * (q * (1 - q) + (q - k / n) / 3))
        return math.exp(-a * n)
    if method == "bound":  # Chernoff with relative entropy
        x = k / n
        return math.exp(-n * (x * math.log(x / q) + (1 - x) * math.log((1 - x) / (1 - q))))
    return math.exp(log_binom_cdf(k, n, q))


def estimate_threshold(spec: SketchSpec, eps: float) -> float | None:
    """The base estimate below which a state violates, for sketches whose estimate is a falling function of pi.

    None where that does not hold: adaptive sampling and bitmaps, and registers at a bound that falls in the range of
    their small-count correction.
    """
    q, k = pi0(eps), spec.k
    if spec.kind == "linear":
        return -k * math.log(q)
    if spec.kind == "bottomk":
        return (k - 1) / q
    if spec.kind == "hll":
        from ..operators.sketches import hll_alpha

        at = hll_alpha(k) * k / q
        return at if at > 2.5 * k else None
    return None


def min_n_for_delta(spec: SketchSpec, eps: float, target: float, method: str = "exact") -> int:
    """Least n whose failure probability is at most ``target``."""
    low = math.floor(min_cardinality(spec.k_max, eps))
    high = 2 * low + 2
    while delta(spec, high, eps, method) > target:
        high *= 2
    while high - low > 1:
        mid = (low + high) // 2
        low, high = (low, mid) if delta(spec, mid, eps, method) <= target else (mid, high)
    return high


def variance_bound(n: float, v: float, c: float, rate: float) -> float:
    """Variance of a thinned estimate with v phantoms, from a base of variance n^2 / c."""
    return (n + v) ** 2 / c + (n + v) * (1 - rate) / rate * (1 + 1 / c)
