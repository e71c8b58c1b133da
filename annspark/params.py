"""Parameters of the subspace-collision methods, and the named methods as presets."""

from __future__ import annotations

from dataclasses import asdict, dataclass, replace
from math import ceil, isqrt


@dataclass(frozen=True)
class Params:
    """``ns`` subspaces of ``s`` dimensions, ``cells`` index cells (a square) per subspace, ``t`` clustering rounds,
    collision ratio ``alpha``, re-rank ratio ``beta``, ``k`` neighbours; then the choices that tell the methods apart."""

    ns: int = 6
    s: int = 8
    cells: int = 256
    t: int = 5
    alpha: float = 0.1
    beta: float = 0.1
    k: int = 10
    space: str = "adaptive"  # adaptive | agnostic | sampled
    activation: str = "heap"  # heap | linear | windowed | exact (no index)
    selector: str = "cutoff"  # cutoff | fixed
    rule: str = "lookahead"  # lookahead | accumulate
    probe: str = "codes"  # codes | postings | auto
    cell_distance: str = "l2"  # l2 | l2sq
    init: str = "spread"  # spread | random | kmeans++
    min_candidates: int = 0
    seed: int = 17

    def __post_init__(self):
        if isqrt(self.cells) ** 2 != self.cells or self.cells < 1:
            raise ValueError("cells must be a perfect square")
        if not (0 < self.alpha <= 1 and 0 < self.beta <= 1 and self.k >= 1 and self.ns >= 1 and self.s >= 2):
            raise ValueError("alpha and beta lie in (0, 1], k and ns are at least 1, s is at least 2")
        for value, allowed in ((self.space, ("adaptive", "agnostic", "sampled")), (self.activation, ("heap", "linear", "windowed", "exact")), (self.selector, ("cutoff", "fixed")), (self.rule, ("lookahead", "accumulate")), (self.probe, ("codes", "postings", "auto")), (self.cell_distance, ("l2", "l2sq"))):
            if value not in allowed:
                raise ValueError(f"{value!r} is none of {allowed}")

    @property
    def side(self) -> int:
        """Centroids of each half of a subspace."""
        return isqrt(self.cells)

    def collisions(self, n: int) -> int:
        return max(1, ceil(self.alpha * n))

    def budget(self, n: int) -> int:
        return max(1, int(self.beta * n))

    def to(self, **changes) -> Params:
        return replace(self, **changes)

    def as_dict(self) -> dict:
        return asdict(self)


PRESETS = {
    "adaptive": {"space": "adaptive", "activation": "heap", "selector": "cutoff"},
    "agnostic": {"space": "agnostic", "activation": "linear", "selector": "fixed"},
    "agnostic+transform": {"space": "adaptive", "activation": "linear", "selector": "fixed"},
    "agnostic+cutoff": {"space": "agnostic", "activation": "linear", "selector": "cutoff"},
    "agnostic+query": {"space": "agnostic", "activation": "heap", "selector": "cutoff"},
    "collision_scan": {"space": "agnostic", "activation": "exact", "selector": "fixed"},
}


def preset(name: str, **changes) -> Params:
    return Params(**{**PRESETS[name], **changes})
