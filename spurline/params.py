"""Parameters of the branch-aware clustering, with their allowed values."""

from __future__ import annotations

import json
from dataclasses import asdict, dataclass

ALLOWED = {
    "cluster_selection": {"eom", "leaf"}, "branch_selection": {"eom", "leaf"}, "graph": {"core", "full", "mutual"}, "combine": {"average", "product"},
    "central_labels": {"centre", "geodesic"}, "eccentricity": {"geometric", "geodesic", "distance_sum", "max_path"}, "edge_length": {"distance", "mreach", "hops"},
    "metric": {"euclidean", "manhattan", "chebyshev", "angular"}, "root": {"nearest_centroid", "extremal"}, "direction": {"max", "min"},
}


@dataclass(frozen=True)
class BranchParams:
    min_samples: int = 5
    min_cluster_size: int = 25
    min_branch_size: int | None = None
    allow_single_cluster: bool = False
    cluster_selection: str = "eom"
    branch_selection: str = "eom"
    cluster_epsilon: float = 0.0
    branch_persistence: float = 0.0
    graph: str = "core"
    label_sides: bool = False
    combine: str = "average"
    central_labels: str = "centre"
    eccentricity: str = "geometric"
    root: str = "nearest_centroid"
    direction: str = "max"
    smooth: int = 0
    push: bool = False
    metric: str = "euclidean"
    edge_length: str = "distance"
    with_tree_edges: bool = True
    temperature: float = 1.0

    def __post_init__(self):
        for name, allowed in ALLOWED.items():
            if getattr(self, name) not in allowed:
                raise ValueError(f"{name} must be one of {sorted(allowed)}")
        if self.min_samples < 1 or self.min_cluster_size < 2 or self.branch_size < 2 or self.temperature <= 0:
            raise ValueError("sizes must be at least 2, min_samples at least 1, temperature positive")

    @property
    def branch_size(self) -> int:
        return self.min_branch_size or self.min_cluster_size

    def to_json(self) -> str:
        return json.dumps(asdict(self), sort_keys=True)
