"""Index settings and table schemas."""

from __future__ import annotations

from dataclasses import asdict, dataclass

#: Reserved partition of vectors that no flush or rebuild has placed yet.
DELTA_ID = -1
#: Fixed-point scale of summed components: sums of integers do not depend on their order.
FIXED_POINT = 1 << 30

VECTORS = "part_id long, asset_id long, vec_id long, embedding array<float>, seq long"
CENTROIDS = "part_id long, centroid array<double>, n_members long, super_id long"
TOMBSTONES = "asset_id long, seq long"


@dataclass(frozen=True)
class IndexConfig:
    """How an index is trained.

    ``penalty`` is one of none, multiplicative, additive, cap; ``scope`` frozen (counts fixed within a
    batch) or sequential; ``sampling`` exact_md5 (exactly ``batch`` rows an iteration) or one_pass
    (each row tested against a threshold, ``batch`` rows in expectation).
    """

    metric: str = "l2"
    target_size: int = 100
    batch: int = 64
    iters: int = 6
    seed: int = 42
    penalty: str = "multiplicative"
    lam: float = 0.5
    cap: float = 2.0
    scope: str = "frozen"
    sampling: str = "exact_md5"
    balanced_final: bool = False

    def as_dict(self) -> dict:
        return asdict(self)
