"""Parameters of a ranking run."""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class RankConfig:
    """Damping, tolerances and limits; the defaults are the published ones.

    ``tol_mode='scaled'`` divides the tolerance by the number of vertices: on a
    graph of 2e11 vertices the mean rank lies below 1e-10, and an absolute test
    would stop at once.  ``frontier_rows`` is the most vertices that a frontier
    may have to be broadcast; larger ones are joined where the edges lie.  Neither
    way changes a result.
    """

    alpha: float = 0.85
    tol: float = 1e-10
    tol_frontier: float = 1e-6
    tol_prune: float = 1e-6
    max_iter: int = 500
    norm: str = "linf"
    tol_mode: str = "absolute"
    layout: str = "none"
    split_degree: int = 64
    salts: int = 8
    frontier_rows: int = 100_000

    def bar(self, n: int) -> float:
        return self.tol / n if self.tol_mode == "scaled" else self.tol
