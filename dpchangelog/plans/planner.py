"""Choice of a sliding plan by exact worst-case variance, and a readable account of a release."""

from __future__ import annotations

import math
from dataclasses import dataclass
from functools import lru_cache

from ..functions.intervals import div_int
from .accounting import Budget, ceil_int, folds_sliding_b, folds_sliding_k, folds_tree_b, folds_tree_k, height_for


def cover(l: int, r: int, c: int, h: int) -> list[tuple[int, int]]:
    """Nodes (layer, index) whose intervals make up (l, r], each as high as it goes below layer h.

    At layer j the whole nodes within the range are ceil(l / c^j) up to floor(r / c^j); those under a whole node of the layer
    above are left to it.
    """
    out = []
    for j in range(h):
        lo, hi = ceil_int(l, c**j), r // c**j
        if hi <= lo:
            continue
        if j == h - 1:
            out += [(j, i) for i in range(lo, hi)]
            continue
        up_lo, up_hi = ceil_int(l, c ** (j + 1)) * c, r // c ** (j + 1) * c
        if up_hi <= up_lo:
            out += [(j, i) for i in range(lo, hi)]
        else:
            out += [(j, i) for i in (*range(lo, min(hi, up_lo)), *range(max(lo, up_hi), hi))]
    return out


@lru_cache(None)
def worst_cover(length: int, c: int, h: int) -> int:
    """Most nodes over all offsets of a range of so many base intervals.

    Of n nodes in a row at a layer, those that no whole parent holds are n mod c, or c more where two parents at the ends can
    leave out as many (c - 1 each). Which of the two is free at each layer, so two lengths a layer are all that occur.
    """
    most = {length: 0}
    for _ in range(h - 1):
        above: dict[int, int] = {}
        for n, nodes in most.items():
            for loose in (n % c, n % c + c):
                if loose <= min(n, 2 * c - 2):
                    k = (n - loose) // c
                    above[k] = max(above.get(k, 0), nodes + loose)
        most = above
    return max(n + nodes for n, nodes in most.items())


@dataclass(frozen=True)
class Plan:
    kind: str
    c: int
    h: int
    eps_node: float
    worst_variance: float


def choose_sliding_plan(w: int, p: int, total_eps: float, k: int | None = None, b: int | None = None, fanouts=range(2, 65)) -> Plan:
    """Least worst-case variance at a total budget (basic composition, Laplace of sensitivity 1 a node).

    Looks at the direct release, the flat one (base intervals added up) and trees of every fan-out and height up to the
    least that holds a window. Plans are compared by nodes times folds squared, in whole numbers; the first of equals is taken.
    """
    g = math.gcd(w, p)
    n = w // g
    folds = lambda kind, c, h: (folds_sliding_k(k, w, p) if b is None else folds_sliding_b(b, w, p)) if kind == "direct" else folds_tree_k(h, k) if b is None else folds_tree_b(h, c, b, g)
    options = [("direct", 1, 1, 1), ("flat", 2, 1, n)]
    for c in fanouts:
        h = 2
        while c ** (h - 1) < n:
            options.append(("tree", c, h, worst_cover(n, c, h)))
            h += 1
    kind, c, h, nodes = min(options, key=lambda x: x[3] * folds(*x[:3]) ** 2)
    eps = total_eps / folds(kind, c, h)
    return Plan(kind, c, h, eps, nodes * 2 / eps**2)


def explain_release(name: str, folds: int, per_query: Budget, variance: float) -> str:
    return f"{name}: {folds} folds; each query ({per_query.eps:g}, {per_query.delta:g}); in all ({folds * per_query.eps:g}, {folds * per_query.delta:g}); variance of a node {variance:g}"


def prefix_nodes(r, c: int, h: int):
    """Nodes of the prefix (0, r], a number or a column: whole nodes of a layer less those under whole parents, c for each."""
    return r - (c - 1) * sum((div_int(r, c**j) for j in range(1, h)), 0)


def fanout_sweep(n: int, fanouts=range(2, 65)) -> list[tuple[int, int, int, float]]:
    """(c, h, worst nodes of a prefix or range, h^2 times it): the variance of a tree over n intervals at one total budget."""
    out = []
    for c in fanouts:
        h = height_for(n, c)
        nodes = max(prefix_nodes(r, c, h) for r in range(1, n + 1))
        out.append((c, h, nodes, float(h * h * nodes)))
    return out


def best_fanout(n: int, fanouts=range(2, 65)) -> int:
    return min(fanout_sweep(n, fanouts), key=lambda x: x[3])[0]


@dataclass(frozen=True)
class ReleaseSpec:
    """What a release promises: n intervals (None: without end), and whether later queries may depend on earlier answers."""

    name: str
    n: int | None = None
    adaptive: bool = False

    def budget(self, per_query: Budget, folds: int | None, method: str = "basic", slack: float = 0.0) -> Budget:
        """Total of the folds an entry touches; without a bound on folds, that of all n queries."""
        from . import accounting as A

        k = folds if folds is not None else self.n
        if k is None:
            raise ValueError("an endless release of unconstrained entries has no finite budget")
        if method == "optimal":
            return min((x for x in A.compose_optimal(per_query, k, self.adaptive) if x.delta <= slack), key=lambda x: x.eps)
        return A.compose_advanced(per_query, k, slack) if method == "advanced" else A.fold(k, per_query)
