"""Parameters of a private release and their checks."""

from __future__ import annotations

from dataclasses import dataclass, replace

#: Default target size, accepted upper budget.
WIDTH, HEIGHT, BUDGET_LIMIT = 47, 62, 9.0


@dataclass(frozen=True)
class ReleaseParams:
    nc: int
    eps: float | None
    key: str
    release_id: str = "r1"
    irw: int = WIDTH
    irh: int = HEIGHT
    imthresh: int = 1
    train: float = 0.7
    delta_mode: str = "index"
    scope: str = "component"
    domain: str = "score"
    clip: bool = True
    ddof: int = 1
    enforce_cap: bool = True
    allow_extreme: bool = False
    snap: float | None = None


def check_budget(eps: float | None, limit: float = BUDGET_LIMIT, allow_extreme: bool = False) -> float | None:
    """Budgets in (0, limit]; None means no noise; more than the limit needs ``allow_extreme``."""
    if eps is None:
        return None
    if not eps > 0:
        raise ValueError("the budget must be positive")
    if eps > limit and not allow_extreme:
        raise ValueError(f"a budget over {limit} needs allow_extreme=True")
    return float(eps)


def resolve_target(irw: int, irh: int, w_min: int, h_min: int, mode: str = "literal") -> tuple[int, int]:
    """M2: both minima replace the target if either side asked for is below its minimum.

    ``per_side`` raises only the side that is below.
    """
    if mode == "per_side":
        return max(irw, w_min), max(irh, h_min)
    return (w_min, h_min) if irw < w_min or irh < h_min else (irw, irh)


def cap_components(nc: int, irw: int, irh: int, enforce: bool = True) -> int:
    """M5: no more components than the smaller side has pixels, unless not enforced."""
    return min(nc, irw, irh) if enforce else nc


def resolve(params: ReleaseParams, channels: int = 1) -> ReleaseParams:
    """Checked parameters with the component cap applied."""
    check_budget(params.eps, allow_extreme=params.allow_extreme)
    if params.nc < 1:
        raise ValueError("at least one component is needed")
    nc = cap_components(params.nc, params.irw, params.irh, params.enforce_cap)
    if nc > params.irw * params.irh * channels:
        raise ValueError("more components than pixels")
    return replace(params, nc=nc)
