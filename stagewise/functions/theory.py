"""Bounds and costs of membership filters, in bits per positive key.

``lam`` is the number of negatives per positive, ``eps`` the false-positive rate, ``C`` the cells an XOR table spends per key. Every
function takes numbers or Spark columns and gives the same kind back.
"""

from __future__ import annotations

import functools
import math
from collections.abc import Callable, Sequence
from dataclasses import dataclass
from itertools import combinations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Fixed values.
LN2 = math.log(2.0)
BLOOM_FACTOR = 1 / LN2
C_UNIFORM, C_COUPLED, COUPLED_WINDOW = 1.23, 1.13, 120
COUPLED_THRESHOLDS = {3: 1.12, 4: 1.05}
EDGE_MAP_BITS, COLOUR_MAP_BITS, CUCKOO_FACTOR = 2.33, 2.2, 1.05
LOCKING_BITS_PER_BUCKET = 8

Num = float | Column


def _col(*xs) -> bool:
    return any(isinstance(x, Column) for x in xs)


def _lit(x) -> Column:
    return x if isinstance(x, Column) else F.lit(float(x))


def log2(x: Num) -> Num:
    return F.log2(x) if _col(x) else math.log2(x)


def exp(x: Num) -> Num:
    return F.exp(x) if _col(x) else math.exp(x)


def floor(x: Num) -> Num:
    return F.floor(x).cast("double") if _col(x) else float(math.floor(x))


def power2(x: Num) -> Num:
    return F.pow(F.lit(2.0), x) if _col(x) else 2.0**x


def least(*xs: Num) -> Num:
    return F.least(*map(_lit, xs)) if _col(*xs) else min(xs)


def where(cond, yes: Callable[[], Num], no: Callable[[], Num]) -> Num:
    """``yes`` or ``no``; each is evaluated only where it is chosen, as it may not be defined elsewhere."""
    if _col(cond):
        return F.when(cond, _lit(yes())).otherwise(_lit(no()))
    return yes() if cond else no()


# --- information bounds ----------------------------------------------------------------------------------------------------


def entropy2(p: Num) -> Num:
    inside = (p > 0) & (p < 1)
    return where(inside, lambda: -p * log2(p) - (1 - p) * log2(1 - p), lambda: 0.0)


def class_bits(t: Num) -> Num:
    """Bits per positive that tell the positives from ``t`` times as many negatives."""
    return where(t > 0, lambda: (t + 1) * entropy2(1 / (t + 1)), lambda: 0.0)


def lb(eps: Num, lam: Num) -> Num:
    """What any filter of rate ``eps`` needs at least."""
    return class_bits(lam) - class_bits(eps * lam)


def lb_approx(eps: Num) -> Num:
    return -log2(eps)


def lb_exact(lam: Num) -> Num:
    return class_bits(lam)


def split_gap(e1: Num, e2: Num, lam: Num) -> Num:
    """What a split into stages of rates e1 and e2 loses: nothing, up to rounding."""
    return lb(e1, lam) + lb(e2, e1 * lam) - lb(e1 * e2, lam)


def split_many(rates: Sequence[float], lam: Num) -> Num:
    """The sum of the bounds of consecutive stages."""
    total, left = 0.0, lam
    for e in rates:
        total = total + lb(e, left)
        left = e * left
    return total


def swap_roles(n: Num, u: Num) -> Num:
    """Negatives per positive when the rarer class counts as the positive one."""
    if _col(n, u):
        return F.greatest(_lit(n), _lit(u) - _lit(n)) / F.least(_lit(n), _lit(u) - _lit(n))
    return max(n, u - n) / min(n, u - n)


def toy_bound(u: int, n: int) -> tuple[int, float]:
    """For a universe small enough to list: the number of positive sets, and the bits that tell them apart."""
    sets = sum(1 for _ in combinations(range(u), n))
    return sets, math.log2(sets)


def dynamic_gap(c_eps: Num, lam: Num, eps: Num) -> Num:
    """How much more a dynamic approximate filter with ``c_eps`` bits over the static bound costs than an exact static pair."""
    return c_eps + lb_approx(eps) - lb(eps, lam)


# --- XOR tables ------------------------------------------------------------------------------------------------------------


@functools.cache
def peel_threshold(j: int = 3) -> float:
    """Cells per key above which random j-slot tables peel: j x / (-ln(1 - y)) terms, minimised by golden section."""
    f = lambda x: -math.log1p(-x) / (j * x ** (j - 1))  # noqa: E731  keys per cell at which survivors of share x are self-sustaining
    lo, hi, g = 1e-6, 1 - 1e-9, (math.sqrt(5) - 1) / 2
    for _ in range(200):
        a, b = hi - g * (hi - lo), lo + g * (hi - lo)
        lo, hi = (lo, b) if f(a) < f(b) else (a, hi)
    return 1 / f((lo + hi) / 2)


def coupled_threshold(j: int = 3) -> float:
    return COUPLED_THRESHOLDS[j]


def partial_a(eps: Num, lam: Num, C: Num = 1.0) -> Num:
    """One exact table with fair-coin answers that encodes all but the negatives which may pass."""
    return C * (lam + 1 - 2 * eps * lam)


def partial_b(eps: Num, lam: Num, C: Num = 1.0) -> Num:
    """One exact table with constant answers, by the rate claimed for it."""
    return C * (lam + 1) / (eps * lam + 1)


def cost_single(eps: Num, lam: Num, C: Num = 1.0) -> Num:
    """The best single table: approximate, or exact on part of the negatives."""
    return where(
        eps > 0,
        lambda: least(C * -log2(eps), where(eps <= 0.5, lambda: partial_a(eps, lam, C), lambda: C * -log2(eps))),
        lambda: C * (lam + 1),
    )


def cost_staged(lam: Num, C: Num = 1.0) -> Num:
    return where(lam * LN2 > 1, lambda: C * log2(2 * math.e * lam * LN2), lambda: C * (lam + 1))


def cost_staged_int(lam: Num, C: Num = 1.0) -> Num:
    """With whole fingerprint bits."""
    k = lambda: floor(log2(lam))
    return where(lam >= 1, lambda: C * (k() + 1 + lam / power2(k())), lambda: C * (lam + 1))


def staged_overhead(lam: Num, C: Num = 1.0) -> Num:
    return cost_staged_int(lam, C) / lb_exact(lam)


#: The largest ratio of the staged cost to the bound at C = 1, reached at lam = 4.
MAX_OVERHEAD = 4 / (5 * math.log2(5) - 8)


def general_a(eps: Num, lam: Num, C: Num = 1.0) -> Num:
    def approx() -> Num:
        return where(eps > 0, lambda: C * -log2(eps), lambda: C * (lam + 1))

    inside = (lam > 1 / LN2) & (2 * eps * lam * LN2 < 1)
    return where(inside, lambda: C * (log2(2 * math.e * lam * LN2) - 2 * lam * eps), lambda: least(approx(), where(eps <= 0.5, lambda: partial_a(eps, lam, C), approx)))


def general_b(eps: Num, lam: Num, C: Num = 1.0) -> Num:
    s = eps * lam / (eps * lam + 1)

    def approx() -> Num:
        return where(eps > 0, lambda: C * -log2(eps), lambda: C * (lam + 1))

    inside = (eps < LN2) & (lam * (LN2 - eps) > 1)
    return where(inside, lambda: C * (log2(2 * math.e * lam * LN2 / (eps * lam + 1)) - s), lambda: least(approx(), partial_b(eps, lam, C)))


def cost_general(eps: Num, lam: Num, C: Num = 1.0, strategy: str = "best") -> Num:
    return {"a": general_a, "b": general_b}[strategy](eps, lam, C) if strategy != "best" else least(general_a(eps, lam, C), general_b(eps, lam, C))


def bound_drop(eps: Num, lam: Num) -> Num:
    """A loose bound: give up an ``eps`` share of the negatives, be exact on the rest."""
    return lb_exact((1 - eps) * lam)


def bound_groups(eps: Num, lam: Num, t: int) -> Num:
    """A loose bound: ``t`` groups of negatives, a filter for each."""
    return t * lb(eps, lam / t)


@dataclass(frozen=True)
class Step:
    """One stage of a plan: kind of filter and its false-positive rate."""

    kind: str
    eps: float


def plan_chain(eps: float, lam: float, m: int | None = None) -> tuple[list[Step], float]:
    """AND of m XOR tables: all rates one half but the last, which makes up the rest; and its cost per key and cell."""
    if m is None:
        m = max(1, math.floor(math.log2(lam)) + 1) if lam >= 1 else 1
        if eps > 0:
            m = min(m, math.floor(-math.log2(eps)) + 1)
    rates = [0.5] * (m - 1) + [min(1.0, 2.0 ** (m - 1) * eps)]
    steps = [Step("xor", e) for e in rates[:-1]] + [Step("retrieval", rates[-1])]
    return steps, (m - 1) + 1 + lam / 2 ** (m - 1) - 2 * eps * lam


def and_envelope(cost: Callable[[float, float], float], eps: float, lam: float, grid: int = 64) -> float:
    """The least cost of an AND of filters of the given elementary cost, by dynamic programming over rates on a log grid."""
    if eps >= 1:
        return 0.0
    points = [eps ** (i / grid) if eps > 0 else 2.0**-i for i in range(grid + 1)] + ([0.0] if eps == 0 else [])
    best = [0.0] + [math.inf] * (len(points) - 1)
    for i, e1 in enumerate(points):
        for k in range(i + 1, len(points)):
            rate = points[k] / e1
            best[k] = min(best[k], best[i] + cost(rate, e1 * lam))
    return best[-1]


# --- alternating filters, elementary filters, applications -------------------------------------------------------------------


def cost_alternating(lam: Num, delta: float = 0.5, Cp: float = BLOOM_FACTOR) -> Num:
    return Cp * (log2(lam) + (1 + delta) / (1 - delta) * math.log2(1 / delta))


def alternating_limit(lam: Num, Cp: float = BLOOM_FACTOR) -> Num:
    """The limit of the cost as delta goes to one."""
    return Cp * log2(math.e**2 * lam)


def layer_plan(n: int, lam: float, delta: float = 0.5) -> list[tuple[int, float, float]]:
    """(layer, rate, expected bits) until less than one key is expected to be left."""
    out, accepted, rejected, layer = [], float(n), n * lam, 1
    while accepted >= 1 and layer < 64:
        rate = min(0.5, delta / lam) if layer == 1 else delta * delta
        out.append((layer, rate, accepted * BLOOM_FACTOR * -math.log2(rate)))
        accepted, rejected = rejected * rate, accepted
        layer += 1
    return out


def elementary_cost(kind: str, eps: Num = 0.0, lam: Num = 0.0, C: float = 1.0) -> Num:
    """Bits per positive of one filter alone."""
    if kind in ("bloom", "blocked"):
        return BLOOM_FACTOR * -log2(eps)
    if kind == "cuckoo":
        return CUCKOO_FACTOR * (2 - log2(eps))
    if kind == "xor":
        return C * -log2(eps)
    per_item = {"edge_map": EDGE_MAP_BITS, "colour_map": COLOUR_MAP_BITS, "retrieval": C}[kind]
    return per_item * (lam + 1)


def predictor_lambda(r: Num) -> Num:
    """Keys in the first of two tables per key in the second, at load r."""
    return 1 / (2 * r / (1 - exp(-2 * r)) - 1)


def alternating_bound(lam: Num, Cp: float = BLOOM_FACTOR) -> Num:
    """What an alternating filter with whole hash counts needs at most, at delta one half."""
    return Cp * log2(16 * lam)


def predictor_space(r: Num, buckets: float = 1e6) -> Num:
    """Mb of a predictor that knows the table of each key: an alternating filter of the second table's keys, with whole hash counts."""
    lam = predictor_lambda(r)
    return r * buckets / (lam + 1) * alternating_bound(lam) / 1e6


def locking_space(buckets: float = 1e6) -> float:
    return LOCKING_BITS_PER_BUCKET * buckets / 2 / 1e6


def classify(eps: Num, lam: Num) -> Num:
    if _col(eps, lam):
        return F.when(_lit(eps) == 0, "exact").when(_lit(lam) == float("inf"), "approximate").otherwise("general")
    return "exact" if eps == 0 else "approximate" if math.isinf(lam) else "general"


def entropy_of(df: DataFrame, symbol: str) -> DataFrame:
    """One row: n, distinct symbols, entropy in bits per symbol."""
    counts = df.groupBy(symbol).agg(F.count(F.lit(1)).alias("c"))
    total = counts.agg(F.sum("c").alias("n"))
    return counts.crossJoin(F.broadcast(total)).groupBy("n").agg(  # one row: the number of symbols
        F.count(F.lit(1)).alias("symbols"), F.sum(-(F.col("c") / F.col("n")) * F.log2(F.col("c") / F.col("n"))).alias("entropy")
    )


def code_len_bounds(entropy: Num) -> tuple[Num, Num]:
    """Between which lengths a staged filter stores a symbol of that entropy: at least the entropy, less than 0.22 bit above."""
    return entropy, entropy + 0.22


def complexity_table(spark: SparkSession) -> DataFrame:
    rows = [
        ("xor_approximate", "O(n)", "C n log2(1/eps)", "O(n log n)"),
        ("xor_exact", "O(u)", "C u", "O(u log u)"),
        ("staged", "O(u)", "C n log2(2 e lam ln2)", "O(n log n)"),
        ("alternating", "O(u loglog n)", "C' n log2(16 lam)", "O(1)"),
    ]
    return spark.createDataFrame(rows, "filter string, time string, space string, extra_space string")


@dataclass(frozen=True)
class Plan:
    kind: str
    steps: tuple[Step, ...]
    negate: bool
    bits_per_positive: float


def plan(n: int, u: int, eps: float = 0.0, dynamic: bool = False, C: float = C_UNIFORM, budget: float | None = None) -> Plan:
    """Kind and parameters for n positives among u keys: staged, or its degenerate forms; roles are swapped if positives are the majority.

    A ``budget`` of bits that the plan would exceed buys an approximate table of as many fingerprint bits as it pays for.
    """
    best = _within_rate(n, u, eps, dynamic, C)
    rarer = min(n, u - n) if best.negate else n
    if budget is None or best.bits_per_positive * max(1, rarer) <= budget:
        return best
    bits = math.floor(budget / (C * max(1, n)))
    if bits < 1:
        raise ValueError(f"{budget} bits are less than one cell for each of {n} keys")
    return Plan("single", (Step("xor", 2.0**-bits),), False, C * bits)


def _within_rate(n: int, u: int, eps: float, dynamic: bool, C: float) -> Plan:
    negatives = max(0, u - n)
    negate = eps == 0 and 0 < negatives < n
    if negate:
        n, negatives = negatives, n
    lam = negatives / max(1, n)
    exact = "edge_map" if dynamic else "retrieval"
    if eps == 0 and lam * LN2 <= 1:
        return Plan("single", (Step(exact, 0.0),), negate, C * (lam + 1))
    if eps > 0 and (2 * eps * lam * LN2 >= 1 or lam * LN2 <= 1):
        return Plan("single", (Step("bloom" if dynamic else "xor", eps),), negate, C * -math.log2(eps))
    k = math.floor(math.log2(lam))
    if k == 0:
        return Plan("single", (Step(exact, eps),), negate, C * (lam + 1))
    return Plan("staged", (Step("bloom" if dynamic else "xor", 2.0**-k), Step(exact, min(1.0, eps * 2**k))), negate, C * (k + 1 + lam / 2**k))
