"""Column expressions of the estimators."""

from __future__ import annotations

from pyspark.sql import Column, functions as F


def discovery_weight(load: Column, budget: int) -> Column:
    """Inverse chance that a worker with ``load`` edges before the closing one still holds both others."""
    return F.when(load <= budget, F.lit(1.0)).otherwise(load.cast("double") * (load - 1) / F.lit(float(budget) * (budget - 1)))


def edge_slot(rank: Column, budget: int, u01: Column) -> Column:
    """Slot the edge of this rank asks for: its own while there is room, then a uniform one of ``rank``."""
    return F.when(rank <= budget, rank).otherwise((F.floor(u01 * rank) + 1).cast("bigint"))


def counting_worker(fu: Column, fv: Column, fw: Column) -> Column:
    """The one worker that can count a triangle closed by (u, v) with apex w."""
    return F.when(fu == fv, fu).otherwise(fw)


def canonical(u: Column, v: Column) -> tuple[Column, Column]:
    return F.least(u, v), F.greatest(u, v)


def pairs_of(n: Column) -> Column:
    """n choose 2."""
    return (n * (n - 1) / 2).cast("bigint")
