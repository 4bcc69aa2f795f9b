"""Parameters with their defaults. Those marked given are printed in the reference; the others are tuned on the simulator."""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class Params:
    # given
    sample_rate_hz: float = 10.0
    window_size: int = 100
    epochs_max: int = 50
    w_min: float = 0.55
    w_max: float = 5.0
    tray_net: float = 4.25
    step_m: float = 0.3048
    max_degree: int = 3
    min_score: float = 0.94
    spacing_a: float = 1.63
    spacing_b: float = 1.22
    # tuned
    z_limits: float = 1.96
    eps: float = 1.0
    min_pts: int = 10
    scale_x: float = 0.8
    scale_y: float = 3.0
    scale_t: float = 5.0
    tray_min_pts: int = 5
    hampel_half: int = 25
    hampel_sigma: float = 3.0
    mad_floor: float = 0.0
    prominence_m: float = 5.0
    peak_distance: int = 50
    overlap_m: float = 5.0
    max_rate: float = 0.5
    median_half: int = 2
    gap_cap_s: float = 5.0
    tray_scale_t: float = 30.0
    tray_scale_y: float = 3.0
    tray_scale_w: float = 0.5
    tray_scale_row: float = 0.5
    #: Options of steps 3 and 5; off as in the printed listings.
    require_interleaving: bool = False
    keep_plateaus: bool = False


DEFAULT = Params()
