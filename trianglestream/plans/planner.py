"""Choice of parameters."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

#: Tolerance that serves most graphs.
THETA = 0.2


def budget_fraction(edges: DataFrame, fraction: float) -> int:
    """A share of the stream as a number of edges, two at least."""
    return max(2, int(edges.agg(F.count(F.lit(1))).first()[0] * fraction))


def recommend(total_storage: int, method: str = "routed", most_workers: int = 1000, most_per_worker: int = 100_000_000) -> dict[str, float]:
    """Split a total number of stored edges: workers first for the routed estimator, budget first for the average."""
    if method == "routed":
        k = max(1, min(most_workers, total_storage // 2))
        return {"k": k, "budget": max(2, min(most_per_worker, total_storage // k)), "theta": THETA}
    budget = max(2, min(most_per_worker, total_storage))
    return {"k": max(1, total_storage // budget), "budget": budget, "theta": 0.0}
