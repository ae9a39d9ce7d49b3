"""Closed forms: expected dirty words, savings from sorting, query cost ratios, advice."""

from __future__ import annotations

import math

from bitsort.operators.codes import cap_k, min_bitmaps, sufficient_bitmaps


def expected_dirty(r: float, bitmaps: float, n: int, w: int = 32) -> float:
    """Dirty words of r random ones over ``bitmaps`` bitmaps of n bits."""
    cells = bitmaps * n
    if not r or not cells:
        return 0.0
    return -math.expm1(w * math.log1p(-min(r / cells, 1 - 1e-15))) * cells / w


def saving_model(n: int, n_i: int, k: int = 1, w: int = 32) -> float:
    """Storage saved by sorting one uniform column: twice the dirty words it had, less 4 n_i."""
    return 2 * expected_dirty(k * n, sufficient_bitmaps(n_i, k), n, w) - 4 * n_i


def best_cardinality(n: int, w: int = 32, k: int = 1, how: str = "closed") -> int:
    """Cardinality of the largest saving: the published closed form, or the maximum of the model."""
    if how == "closed":
        return round((n * (w - 1) / 2) ** (k / (k + 1)))
    return max(range(2, n), key=lambda c: saving_model(n, c, k, w))


def sorted_cost_bound(n_i: int, k: int = 1) -> int:
    """Storage cost of a sorted column: 2 n_i dirty words and as many clean runs, and one run a bitmap."""
    return 5 * n_i if k == 1 else 4 * n_i + sufficient_bitmaps(n_i, k)


def query_cost_ratio(n_i: int, k: int, kind: str = "estimate") -> float:
    """Cost of an equality query with k bitmaps against k = 1: ``bound``, ``estimate``, ``heap`` or ``absolute``."""
    power = n_i ** ((k - 1) / k)
    if kind == "bound":
        return 3 * (2 * k - 1) * power
    if kind == "estimate":
        return (2 - 1 / k) * power
    if kind == "heap":
        return max(1.0, math.log2(k)) * power
    return (2 - 1 / k) * n_i ** (-1 / k)


def dirty_tradeoff(values: int, total: int, k: int) -> dict[str, int]:
    """A word of ``values`` distinct values of ``total``: dirty words of unary and at most of k-of-N codes."""
    return {"unary": values, "k_of_n": min(min_bitmaps(total, k), k * values), "run_switch": 2 * k}


def column_density(n_i: int, k: int) -> float:
    return n_i ** (-1 / k)


def density_score(n_i: int, k: int, w: int = 32) -> float:
    """Peaks at a density of 1 / (4w): columns with the highest score come first."""
    d = column_density(n_i, k)
    return min(d, (1 - d) / (4 * w - 1))


def column_order(cardinalities: list[int], how: str, k: int = 1, w: int = 32, n: int = 0, skews: list[float] | None = None, heavy: list[int] | None = None) -> list[int]:
    """Indexes of the columns in sort order.

    how: card_asc, card_desc, density, saving, skew, capped_card, heavy_values, capped_power.
    """
    at = list(range(len(cardinalities)))
    if how == "card_asc":
        return sorted(at, key=lambda i: (cardinalities[i], i))
    if how == "card_desc":
        return sorted(at, key=lambda i: (-cardinalities[i], i))
    if how == "density":
        return sorted(at, key=lambda i: (-density_score(cardinalities[i], cap_k(cardinalities[i], k), w), i))
    if how == "saving":
        return sorted(at, key=lambda i: (-saving_model(n, cardinalities[i], cap_k(cardinalities[i], k), w), i))
    if how == "skew":
        order = sorted(at, key=lambda i: ((skews or [0.0] * len(at))[i], cardinalities[i], i))
        return order if k == 1 else order[::-1]
    if how == "capped_card":
        return sorted(at, key=lambda i: (-min(cardinalities[i], n / w), i))
    if how == "heavy_values":
        return sorted(at, key=lambda i: (-(heavy or [0] * len(at))[i], i))
    if how == "capped_power":
        top = max(cardinalities)
        return sorted(at, key=lambda i: (-min(cardinalities[i], k * k * n * (w - 1) / (2 * top)), i))
    raise ValueError(how)


def bitmap_order(densities: list[float], how: str, sizes: list[int] | None = None) -> list[int]:
    """Indexes of bitmaps: IF incompressible, MSF moderately sparse, SF sparse first; set_bits, compressed_size."""
    at = range(len(densities))
    if how == "IF":
        return sorted(at, key=lambda i: (abs(densities[i] - 0.5), i))
    if how == "MSF":
        return sorted(at, key=lambda i: (-min(densities[i], (1 - densities[i]) / (4 * 32 - 1)), i))
    if how in ("SF", "set_bits"):
        return sorted(at, key=lambda i: (densities[i], i))
    if how == "compressed_size":
        return sorted(at, key=lambda i: ((sizes or [0] * len(densities))[i], i))
    raise ValueError(how)


def skew(counts: list[int]) -> float:
    """How skewed a histogram is: the share of rows that two random ones agree on, sum of squared frequencies."""
    n = sum(counts)
    return sum((c / n) ** 2 for c in counts) if n else 0.0


def advise(n: int, cardinalities: list[int], goal: str = "queries") -> dict[str, object]:
    """Which k, allocation and column order to take: unary where queries matter or values are few against rows."""
    few = sum(cardinalities) * 50 < n
    k = 1 if goal == "queries" or few else 2 if goal == "balanced" else 4
    allocation = "freq_reflected" if goal == "space" else "reflected"
    return {"k": k, "allocation": allocation, "columns": column_order(cardinalities, "density", k)}
