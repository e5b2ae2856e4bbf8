"""Parameters of tree construction."""

from __future__ import annotations

from dataclasses import asdict, dataclass

CHOICES = {
    "kind": ("pab", "fpb", "kdt"),
    "axis": ("covariance", "gram"),
    "axis_solver": ("eigh", "power"),
    "offset": ("centred", "printed"),
    "candidate": ("midpoint", "data_mean"),
    "cut": ("sections", "exhaustive"),
    "ball": ("centroid", "enclosing"),
    "kd_axis": ("widest", "cycle", "variance"),
    "kd_cut": ("median", "midpoint"),
    "kd_bounds": ("tight", "cells", "plane"),
    "top": ("auto", "sample", "exact"),
}


@dataclass(frozen=True)
class BuildConfig:
    """How a tree is built.

    kind: principal-axis ball tree (pab), farthest-pivot ball tree (fpb) or KD-tree (kdt).
    kd_bounds: what a search tests a KD-tree's node by: the box of its points (tight), the cell that the cuts
    above it leave (cells), or the last of these cuts alone (plane).
    alpha, sections: weight of the offset term of the split objective and number of sections scanned.
    top: how points reach parts; by one part where they are at most ``local_rows``, else by a tree
    over a sample of ``sample_rows`` points a part, or by exact splits level by level.
    """

    kind: str = "pab"
    leaf_capacity: int = 64
    alpha: float = 0.5
    sections: int = 64
    axis: str = "covariance"
    axis_solver: str = "eigh"
    offset: str = "centred"
    candidate: str = "midpoint"
    cut: str = "sections"
    ball: str = "centroid"
    kd_axis: str = "widest"
    kd_cut: str = "median"
    kd_bounds: str = "tight"
    max_depth: int = 512
    top: str = "auto"
    parts: int | None = None
    local_rows: int = 200_000
    sample_rows: int = 200
    seed: int = 42

    def __post_init__(self):
        for name, allowed in CHOICES.items():
            if getattr(self, name) not in allowed:
                raise ValueError(f"{name} is one of {', '.join(allowed)}, not {getattr(self, name)!r}")
        if self.leaf_capacity < 1 or self.sections < 1 or self.alpha < 0 or self.local_rows < 1:
            raise ValueError("leaf_capacity, sections and local_rows are at least 1, alpha at least 0")

    def params(self) -> dict[str, str]:
        return {k: str(v) for k, v in asdict(self).items()}
