"""Choice between filtering before and after the index."""

from __future__ import annotations

from dataclasses import dataclass

from ivfspark.plans.predicates import Predicate
from ivfspark.plans.statistics import Statistics, selectivity


@dataclass(frozen=True)
class Plan:
    kind: str
    f_filters: float
    f_ivf: float
    reason: str


def ivf_selectivity(n_probe: int, target_size: float, n_rows: int, n_delta: int = 0) -> float:
    """Share of the rows that a search with ``n_probe`` partitions reads; ``n_delta`` adds the delta."""
    return (n_probe * target_size + n_delta) / max(1, n_rows)


def choose(
    predicate: Predicate, stats: Statistics, n_probe: int, target_size: float, threshold: float | None = None, n_delta: int = 0, rule: str = "min_sum"
) -> Plan:
    """pre if the filter narrows more than the index does (strictly), else post."""
    f_filters = selectivity(predicate, stats, rule)
    f_ivf = ivf_selectivity(n_probe, target_size, stats.n, n_delta) if threshold is None else threshold
    if f_filters < f_ivf:
        return Plan("pre", f_filters, f_ivf, "the filter qualifies fewer rows than the index would scan")
    return Plan("post", f_filters, f_ivf, "the index scans no more rows than the filter qualifies")
