"""Rule parameters and the named recipes."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, replace

from pyspark.sql import Column


@dataclass(frozen=True)
class Rule:
    """mode: '1-hop', '2-hop' or 'path'; metric: 'dist', 'angle' or 'rank'; thres: slack alpha (dist) or degrees (angle, 0 for
    greatest dispersion); degree: greatest out-degree; fill: lists are topped up to it; conflict: own predicate instead."""

    mode: str = "1-hop"
    metric: str = "dist"
    thres: float = 1.0
    degree: int = 32
    candidates: int = 128
    fill: bool = False
    kernel: str = "wavefront"
    hop: str = "forward"
    pool: int = 64
    conflict: Callable[[Column, Column, Column], Column] | None = None

    @classmethod
    def dist(cls, thres: float = 1.0, **kw) -> Rule:
        return cls(metric="dist", thres=thres, **kw)

    @classmethod
    def angle(cls, thres: float = 60.0, **kw) -> Rule:
        return cls(metric="angle", thres=thres, **kw)

    @classmethod
    def rank(cls, degree: int = 32, **kw) -> Rule:
        return cls(metric="rank", degree=degree, **kw)

    @classmethod
    def custom(cls, conflict: Callable[[Column, Column, Column], Column], **kw) -> Rule:
        """``conflict(d2 of owner to kept, d2 of owner to candidate, d2 between them)`` is true when the kept one forbids the candidate."""
        return cls(conflict=conflict, **kw)

    def but(self, **kw) -> Rule:
        return replace(self, **kw)


#: The settings of the five compared recipes.
RECIPES = {
    "occlusion_strict": Rule("path", "dist", 1.0, 50),
    "occlusion_relaxed": Rule("path", "dist", 1.2, 32),
    "angle_threshold": Rule("2-hop", "angle", 60.0, 50),
    "angle_dispersion": Rule("1-hop", "angle", 0.0, 32, fill=True),
    "detour_rank": Rule("1-hop", "rank", 0.0, 32, fill=True),
}
