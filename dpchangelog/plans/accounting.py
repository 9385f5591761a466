"""Budgets, composition, and how many queries of a release one entry can touch (fold counts). Fold counts and crossovers take numbers,
or columns of entries' own limits."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F

from ..functions.intervals import ceil_int, div_int, gcd_int, interval_span


@dataclass(frozen=True)
class Budget:
    eps: float
    delta: float = 0.0

    def __post_init__(self):
        if self.eps < 0 or self.delta < 0:
            raise ValueError("a budget isn't negative")

    def __add__(self, o: "Budget") -> "Budget":
        return Budget(self.eps + o.eps, self.delta + o.delta)

    def __le__(self, o: "Budget") -> bool:
        return self.eps <= o.eps and self.delta <= o.delta

    @staticmethod
    def sup(budgets) -> "Budget":
        """Componentwise largest."""
        b = list(budgets)
        return Budget(max((x.eps for x in b), default=0.0), max((x.delta for x in b), default=0.0))


def compose_basic(budgets) -> Budget:
    """Budgets, or nested lists of them: nesting doesn't matter."""
    total = Budget(0.0)
    for b in budgets:
        total = total + (b if isinstance(b, Budget) else compose_basic(b))
    return total


def fold(k: int, b: Budget) -> Budget:
    return Budget(k * b.eps, k * b.delta)


def compose_advanced(b: Budget, k: int, slack: float) -> Budget:
    eps = math.sqrt(2 * k * math.log(1 / slack)) * b.eps + k * b.eps * math.expm1(b.eps)
    return Budget(eps, k * b.delta + slack)


def compose_best(b: Budget, k: int, slack: float) -> Budget:
    """The smaller eps of basic and advanced composition (for a chosen slack)."""
    return min(fold(k, b), compose_advanced(b, k, slack), key=lambda x: x.eps)


def compose_optimal(b: Budget, k: int, adaptive: bool = False) -> list[Budget]:
    """Frontier of (eps, delta) for k equal non-adaptive queries; the sum over outcomes is taken in log space."""
    if adaptive:
        raise ValueError("the frontier holds for queries that are fixed in advance")
    log_c = [math.lgamma(k + 1) - math.lgamma(i + 1) - math.lgamma(k - i + 1) for i in range(k + 1)]
    base = k * math.log1p(math.exp(b.eps))
    out = []
    for i in range(k // 2 + 1):
        eps = (k - 2 * i) * b.eps
        total = sum(math.exp(log_c[j] - base + (k - j) * b.eps) - math.exp(log_c[j] - base + (k - 2 * i + j) * b.eps) for j in range(i))
        out.append(Budget(eps, min(1.0, 1 - (1 - b.delta) ** k * (1 - max(0.0, total)))))
    return out


def zcdp_epsilon(rho: float, k: int, delta: float) -> float:
    r = k * rho
    return r + 2 * math.sqrt(r * math.log(1 / delta))


def renyi_laplace(order: float, scale: float) -> float:
    """Renyi divergence of order > 1 of Laplace noise of sensitivity 1."""
    a, b = order, 1 / scale
    return (1 / (a - 1)) * math.log(a / (2 * a - 1) * math.exp((a - 1) * b) + (a - 1) / (2 * a - 1) * math.exp(-a * b))


def renyi_gaussian(order: float, sigma: float) -> float:
    return order / (2 * sigma * sigma)


def compose_renyi(curve, k: int, delta: float, orders=(1.5, 2, 3, 4, 6, 8, 12, 16, 24, 32, 64, 128)) -> float:
    """eps of k queries, least over the orders; curve: order -> divergence of one."""
    return min(k * curve(a) + math.log(1 / delta) / (a - 1) for a in orders)


# Fold counts, global model. k: at most k mutations an entry; b: all mutations of an entry within b of each other.
def folds_disjoint_k(k: int) -> int:
    return k


def folds_disjoint_b(endpoints, b: int) -> int:
    return interval_span(endpoints, b)


def folds_disjoint_b_regular(b: int, w: int) -> int:
    return ceil_int(b, w) + 1


def folds_tree_k(h: int, k: int) -> int:
    return h * k


def folds_tree_b(h: int, c: int, b: int, w: int, formula: str = "safe") -> float:
    """safe: a whole number, layer by layer. published: the closed form, which can be too small (it rounds once)."""
    if formula == "safe":
        if isinstance(h, Column):
            return F.aggregate(F.sequence(F.lit(0).cast("long"), h - 1), F.lit(0).cast("long"), lambda n, i: n + ceil_int(b, w * F.pow(F.lit(c), i).cast("long")) + 1)
        return sum(ceil_int(b, w * c**i) + 1 for i in range(h))
    return (c**h - 1) / (c**h - c ** (h - 1)) * ceil_int(b, w) + h


def folds_sliding_k(k: int, w: int, p: int) -> int:
    return k * ceil_int(w, p)


def folds_sliding_b(b: int, w: int, p: int) -> int:
    return ceil_int(b + w, p)


def local_folds(global_folds):
    """Two entries differ in all their mutations, so an entry's queries count on both sides."""
    return 2 * global_folds


def hybrid_bound(bounds) -> Budget:
    return Budget.sup(bounds)


def split_budget(total: Budget, folds: int, method: str = "basic", slack: float = 0.0) -> Budget:
    """Budget of each query so that so many folds stay within the total."""
    if method == "basic":
        return Budget(total.eps / folds, total.delta / folds)
    lo, hi = 0.0, total.eps
    for _ in range(200):
        mid = (lo + hi) / 2
        lo, hi = (mid, hi) if compose_best(Budget(mid), folds, slack).eps <= total.eps else (lo, mid)
    return Budget(lo, (total.delta - slack) / folds if total.delta > slack else 0.0)


# Covers and the choice between direct and hierarchical sliding releases.
def layers(c: int) -> range:
    """Layers whose width fits into 64 bits: all that a column of heights can ask for."""
    return range(next(j for j in range(64) if c**j >= 2**63))


def height_for(length: int, c: int) -> int:
    """Least h of 1 or more with c^h >= length; whole numbers, as a logarithm misrounds exact powers."""
    if isinstance(length, Column):
        return F.lit(1).cast("long") + sum((F.lit(c**j) < length).cast("long") for j in layers(c)[1:])
    h, n = 1, c
    while n < length:
        h, n = h + 1, n * c
    return h


def cover_bound(length: int, c: int) -> int:
    """Most nodes that answer a range of so many base intervals."""
    if length <= 0:
        return 0
    return max(1, 2 * (c - 1) * (0 if length == 1 else height_for(length, c)))


def matched_epsilon_k(w: int, p: int, h: int, eps: float) -> float:
    """Budget of a node that spends what the direct release spends at eps a query."""
    return ceil_int(w, p) * eps / h


def matched_epsilon_b(b: int, w: int, p: int, c: int, h: int, eps: float, formula: str = "safe") -> float:
    g = math.gcd(w, p)
    return folds_sliding_b(b, w, p) * eps / folds_tree_b(h, c, b, g, formula)


def prefer_tree_k(w, p, c: int, h=None) -> tuple:
    """(left, right, left < right): the tree has the smaller variance bound if left < right. h: the tree's height where it is known."""
    h = height_for(div_int(w, gcd_int(w, p)), c) if h is None else h
    left, right = 2 * (c - 1) * h**3, ceil_int(w, p) ** 2
    return left, right, left < right


def prefer_tree_b(w, p, b: int, c: int, formula: str = "published", g=None, h=None) -> tuple:
    g = gcd_int(w, p) if g is None else g
    h = height_for(div_int(w, g), c) if h is None else h
    left, right = 2 * (c - 1) * h * folds_tree_b(h, c, b, g, formula) ** 2, ceil_int(b + w, p) ** 2
    return left, right, left < right
