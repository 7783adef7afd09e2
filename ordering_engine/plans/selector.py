"""Choosing a method by the load n / p: published thresholds, or predicted costs under calibrated constants."""

from __future__ import annotations

from pyspark.sql import DataFrame

from . import costs
from .gather import gather_merge_sort
from .gridrank import grid_rank_sort
from .placement import SortResult
from .quicksort import robust_cube_quicksort
from .samplesort import multilevel_samplesort

#: The largest load of each method's range.
PUBLISHED = ((3**-3, "gather_merge"), (4.0, "grid_rank"), (2.0**14, "robust_cube_quicksort"), (float("inf"), "multilevel_samplesort"))
RUN = {"gather_merge": gather_merge_sort, "grid_rank": grid_rank_sort, "robust_cube_quicksort": robust_cube_quicksort, "multilevel_samplesort": multilevel_samplesort}


def choose(n: int, p: int, policy: str = "published", alpha: float = 1.0, beta: float = 1e-3, k: int = 64) -> str:
    load = n / p
    if policy == "published":
        return next(m for most, m in PUBLISHED if load <= most)
    return min(RUN, key=lambda m: costs.cost(m, max(n, 1), p, alpha, beta, min(k, p)))


def adaptive_sort(state: DataFrame, p: int, policy: str = "published", method: str | None = None) -> SortResult:
    """Sort by the method that fits the load; ``method`` overrides the choice."""
    chosen = method or choose(state.count(), p, policy)
    result = RUN[chosen](state, p)
    result.notes["method"] = chosen
    return result
