"""Parameters of a fold; None means that the recording itself decides."""

from __future__ import annotations

from dataclasses import dataclass, replace

from .functions.kernels import field_characteristic


@dataclass(frozen=True)
class FoldConfig:
    pyramid_level: int = 3
    n_neighbors: int = 8
    surrogate: str = "auto"  # raw for one channel, isomap otherwise; distances: all coordinates
    isomap_landmarks: int | None = None  # geodesics from so many frames only
    period: float | None = None
    period_method: str = "acf"
    tmin: int = 3
    tmax: int | None = None
    n_cycles_in_window: int = 1
    d: int | None = None
    sigma: float | None = None
    alpha: float = 0.5
    coeff: int = 7
    max_n: int | None = 200  # windows of an exact barcode; more are covered by landmarks, None: always exact
    kernel: str = "gauss"
    select: str = "zero_cross"
    q: int = 10
    tol: float = 0.2
    cycles: str = "printed"
    M: int | None = None
    F: float | None = None
    anchor: str = "start"
    median: str = "exact"
    tile_px: int = 4096  # pixels of a slab that votes
    gram_tile_px: int | None = None  # sums distances over slabs of so many pixels, for huge frames
    local_frames: int = 2_000  # longer recordings are folded in segments
    local_px: int = 1 << 20  # larger frames are summed over slabs
    overlap: int = 200  # frames that neighbouring segments share
    seed: int = 42

    def __post_init__(self):
        field_characteristic(self.coeff)
        if not 0 <= self.alpha <= 1:
            raise ValueError("alpha is a share")
        for name, allowed in (("kernel", ("gauss", "step", "printed")), ("select", ("zero_cross", "first")), ("median", ("exact", "hist", "approx")), ("surrogate", ("auto", "raw", "isomap", "distances"))):
            if getattr(self, name) not in allowed:
                raise ValueError(f"{name} must be one of {allowed}")

    def but(self, **changes) -> FoldConfig:
        return replace(self, **changes)
