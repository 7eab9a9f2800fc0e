"""Parameters of stable-sample density clustering."""

from __future__ import annotations

from dataclasses import dataclass

CHOICES = {
    "eta_rule": ("monotone", "printed", "plus_one", "fixed"),
    "merge_on": ("core", "any"),
    "weak_edges": ("attach", "connect"),
    "relabel": ("graph", "lazy"),
    "border_rule": ("min_cluster", "nearest_core", "lowest_core_id"),
    "selector": ("rim_and_center", "all_core", "center_only", "rim_only"),
}


@dataclass(frozen=True)
class SsdcParams:
    """eps, min_pts: density; gamma, beta: points of the first sample and of an increment; tau: rim threshold.

    rectify_n, rectify_k: on more than rectify_n points, the test size is that of rectify_n points and rectify_k clusters.
    merge_on: an increment's new cores merge the clusters of their neighbouring cores, or of any neighbour, borders too.
    relabel: clusters follow the graph, or never split. What has merged by "any" or under "lazy" stays merged.
    """

    eps: float
    min_pts: int
    gamma: int
    beta: int
    tau: float = 0.3
    eta_rule: str = "monotone"
    eim_fraction: float = 0.10
    merge_on: str = "core"
    weak_edges: str = "attach"
    relabel: str = "graph"
    border_rule: str = "min_cluster"
    selector: str = "rim_and_center"
    rectify_n: int | None = 50_000
    rectify_k: int | None = 50
    seed: int = 0
    max_iterations: int = 1000
    force_full_minpts: bool = True
    finalize_eta: bool = False
    min_clusters: int = 0
    max_distance: float | None = None

    def validate(self) -> SsdcParams:
        for name, allowed in CHOICES.items():
            if getattr(self, name) not in allowed:
                raise ValueError(f"{name} is one of {allowed}")
        if self.eps <= 0 or self.min_pts < 1 or self.gamma < 1 or self.beta < 1 or not 0 <= self.tau <= 1:
            raise ValueError("eps, min_pts, gamma and beta must be positive, tau within 0 and 1")
        if self.keeps_merges and self.weak_edges == "connect":
            raise ValueError("weak_edges='connect' takes clusters from the graph alone")
        return self

    @property
    def keeps_merges(self) -> bool:
        return self.relabel == "lazy" or self.merge_on == "any"

    @staticmethod
    def of_share(n: int, gamma: float, beta: float, **rest) -> SsdcParams:
        """gamma and beta as shares of n points."""
        return SsdcParams(gamma=-(-int(n * gamma * 1e6) // 10**6) or 1, beta=-(-int(n * beta * 1e6) // 10**6) or 1, **rest)
