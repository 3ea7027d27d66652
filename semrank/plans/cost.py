"""Cost (ranker calls) and recall of each algorithm, for a perfect ranker and random shuffles."""

from __future__ import annotations

import math


def cost_tournament(n: float, k: float, size: int, variant: str = "unit", log_base: float | None = None) -> float:
    """unit: the first bracket, then one call per further winner, which is what runs show. remark and summary: the two printed
    forms, which differ from it and from each other; summary's logarithm is natural unless a base is given."""
    if n <= 1 or k <= 0:
        return 0.0
    first = (n - 1) / (size - 1)
    if variant == "unit":
        return first + (k - 1)
    if variant == "remark":
        return (n + (k - 1) * math.log(n, size)) / (size - 1)
    if variant == "summary":
        log = math.log(n / size) if log_base is None else math.log(n / size, log_base)
        return first + (k - 1) * log
    raise ValueError(variant)


def cost_sort(n: float, size: int, p: int, c: float = 0.1) -> float:
    """n ln n / ((L - P) ln(P + 1)) + c n; one call up to L documents, none for fewer than two."""
    if n <= 1:
        return 0.0
    if n <= size:
        return 1.0
    return n * math.log(n) / ((size - p) * math.log(p + 1)) + c * n


def cost_select(n: float, k: float, size: int, p: int, c: float = 0.0) -> float:
    """One round costs n / (L - P); the bucket with rank K keeps a fraction of the documents, taken as the same each round."""
    if k <= 0 or k >= n:
        return 0.0
    if n <= size:
        return 1.0
    psi = k / n
    return n * (p + 1) / ((size - p) * (p - 1 + psi ** (p + 1) + (1 - psi) ** (p + 1))) + c


def cost_filter(n: int, size: int) -> int:
    return -(-n // size)


def cost_pairwise(n: float, k: float) -> float:
    return 2.5 * n + (k * math.log(k) if k > 1 else 0.0)


def cost_pointwise(n: int) -> int:
    return n


def n_after_filter(n: int, size: int, s: int) -> int:
    """An upper bound: the last bin may be short."""
    return s * -(-n // size)


def _poisson(m: int, lam: float) -> float:
    return math.exp(-lam + m * math.log(lam) - math.lgamma(m + 1)) if lam > 0 else float(m == 0)


def recall_filter(n: int, k: int, size: int, s: int, model: str = "poisson") -> float:
    """Expected share of the top k that survives one round.

    poisson: the capped mean of a bin's relevant documents over its mean; printed: the form as published, which counts the
    bins of exactly S twice and can exceed 1; exact: hypergeometric bins.
    """
    if k <= 0:
        return 1.0
    lam = k * size / n
    if model in ("poisson", "printed"):
        below = sum(_poisson(m, lam) for m in range(s))
        tail = 1 - below if model == "printed" else 1 - below - _poisson(s, lam)
        return below + s / lam * tail
    if model == "exact":
        bins, last = divmod(n, size)

        def capped(width: int) -> float:
            return sum(min(m, s) * math.comb(k, m) * math.comb(n - k, width - m) for m in range(max(0, width - n + k), min(k, width) + 1)) / math.comb(n, width)

        return (bins * capped(size) + (capped(last) if last else 0.0)) / k
    raise ValueError(model)


def sort_condition(p: float, size: int) -> float:
    """Zero where the sort coefficient is least: (P + 1) ln(P + 1) - (L - P)."""
    return (p + 1) * math.log(p + 1) - (size - p)


def best_p_sort(size: int) -> int:
    """The integer that makes 1 / ((L - P) ln(P + 1)) least."""
    return min(range(1, size), key=lambda p: 1 / ((size - p) * math.log(p + 1)))


def best_p_select(n: int, k: int, size: int) -> int:
    if size <= 2 or n <= size or k >= n:
        return 1
    return min(range(1, size), key=lambda p: cost_select(n, k, size, p))


def min_survivors(n: int, k: int, size: int, target: float, model: str = "poisson") -> int | None:
    """The fewest survivors a bin that meet the recall target, by bisection; None if even L - 1 don't."""
    low, high = 1, size - 1
    if recall_filter(n, k, size, high, model) < target:
        return None
    while low < high:
        mid = (low + high) // 2
        low, high = (low, mid) if recall_filter(n, k, size, mid, model) >= target else (mid + 1, high)
    return low


def information(n_items: int) -> tuple[int, float]:
    """Comparisons that a list of so many implies, and the bits of its order."""
    return n_items * (n_items - 1) // 2, math.lgamma(n_items + 1) / math.log(2)
