"""Settings of a run; defaults are those of the published experiments, the rest are choices of this engine."""

from __future__ import annotations

import secrets
from dataclasses import dataclass, replace


@dataclass(frozen=True)
class Cfg:
    """gt_min: slot width. n: window length. eps: budget of one trajectory. theta: how reach depends on the gap.

    theta is one of 'gap' (speed x true gap), 'slot' (speed x one slot), 'fixed' (``theta_fixed_km``), 'inf'.
    eps_mode: 'total' splits eps over the draws, 'per_draw' spends ``eps_draw`` each time.
    delta_mode: 'diameter' keeps the bound; 'unit' is for comparison only and is not private at eps.
    seed: keys all draws; whoever knows it can replay a release. Empty (the default) has every release draw a secret
    one; a given seed is for tests and for comparison with SQL.
    """

    gt_min: int = 10
    n: int = 2
    eps: float = 5.0
    speed_kmh: float = 8.0
    n_poi: int = 2000
    kappa: int = 10
    gs_ladder: tuple[int, ...] = (4, 2, 1)
    t_ladder_h: tuple[int, ...] = (1, 2, 4, 8, 24)
    merge_order: tuple[str, ...] = ("space", "time", "category")
    gamma: int = 50_000
    seed: str = ""
    theta: str = "gap"
    theta_fixed_km: float = 2.0
    eps_mode: str = "total"
    eps_draw: float = 1.0
    delta_mode: str = "diameter"
    fill: str = "reject"
    mbr: bool = True
    overlap: bool = True
    metric: str = "all"
    #: Places or regions above which the dense public arrays are refused.
    dense_regions: int = 4096

    @property
    def slots(self) -> int:
        return 1440 // self.gt_min

    def but(self, **changes) -> "Cfg":
        return replace(self, **changes)

    def secret(self) -> "Cfg":
        """These settings with a seed that nobody knows, unless one is given."""
        return self if self.seed else self.but(seed=secrets.token_hex(16))
