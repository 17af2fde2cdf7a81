"""What a search is asked for."""

from __future__ import annotations

from dataclasses import dataclass, replace


@dataclass(frozen=True)
class SearchSpec:
    """Exactly one of width and theta.  b bounds the successors of an object, so completeness is given up."""

    theta: float | None = None
    width: int | None = None
    k: int = 2
    b: int = 20
    successors: str = "kcnn"  # kcnn | nna | cover | exact
    mode: str = "normal"  # normal | mixed
    heuristic: str = "straight"  # straight | zero
    arity: str = "printed"  # printed: k others; with_source: k - 1 others
    order: str = "features_desc"
    fallback: str = "none"  # none | next_concept
    link_goal: bool = True
    goal_clique: str = "required"  # required | hammock
    pop: int = 4  # objects a search asks for in its first round; what it explores does not depend on it
    reopen: bool | None = None
    t_mode: str = "sum"
    time_limit_s: float = float("inf")  # of a whole batch of pairs; the paper's searches had 120 s each
    max_rounds: int = 200
    max_nodes: int = 100_000

    def __post_init__(self):
        if (self.theta is None) == (self.width is None):
            raise ValueError("exactly one of theta and width")
        if self.k < 2 or self.b < 1:
            raise ValueError("k >= 2 and b >= 1")

    @classmethod
    def simple(cls, **more) -> "SearchSpec":
        """A path whose neighbours share one feature."""
        return cls(width=1, k=2, **more)

    @property
    def others(self) -> int:
        """Members of a successor set besides the object itself."""
        return self.k if self.arity == "printed" else self.k - 1

    @property
    def reopens(self) -> bool:
        return self.mode == "mixed" if self.reopen is None else self.reopen

    def but(self, **changes) -> "SearchSpec":
        return replace(self, **changes)
