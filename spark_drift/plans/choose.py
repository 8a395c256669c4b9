"""Which physical method computes an energy distance, from sizes alone."""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class Choice:
    method: str
    reason: str
    options: dict


def choose(
    n: int, m: int, d: int, pair_budget: float = 1e10, spread: float = 1.0, max_error: float | None = None, cell_budget: float = 1e8
) -> Choice:
    """Exact methods within the pair budget, else the cheapest whose error is known.

    ``spread``: typical width of a feature. A certified error is offered by cells alone; slices and
    samples are taken where no cell size meets both the error and the budget.
    """
    if d == 1:
        return Choice("sorted", "one dimension: exact in one ordering", {})
    pairs = float(n) * m + float(n) * n + float(m) * m
    if pairs <= pair_budget:
        return Choice("pairwise" if d <= 4 else "blocks", f"{pairs:.3g} pairs are within the budget", {})
    if max_error is not None:
        cell = max_error / (2 * d**0.5)
        if (4 * spread / cell) ** (2 * d) <= cell_budget:
            return Choice("cells", f"cells of {cell:.3g} keep the error under {max_error:.3g}", {"cell": cell})
    if (n + m) * 100 <= pair_budget:
        return Choice("sliced", "too many pairs: 100 directions, each exact", {"directions": 100})
    return Choice("sampled", "too many rows for slices: a hash sample of each group", {"cap": int((pair_budget / 3) ** 0.5)})
