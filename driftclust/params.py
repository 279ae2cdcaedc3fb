"""Parameters of the clustering method, with the published defaults."""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class Params:
    """The published defaults of the method."""

    subnets: int = 15
    rho: int = 100
    s: int = 10
    lr_win: float = 0.6
    lr_nbr: float = 0.02
    decay: float = 0.005
    # Options for what the description leaves open.
    seed: int = 1
    seeding: str = "poisson"  # poisson, random, farthest
    strain_at: str = "before"  # distance taken before or after the pull
    keep_split_edge: bool = False
    grow: bool = True
    join: bool = True
    max_neurons: int = 0  # 0: as many as training asks for; else more are refused
    schedule: str = "guided"  # guided, two_stage, adjacent, all_pairs, none
    separability: str = "object"  # object, neuron
    var_floor: float = 1e-6
    min_k: int = 2
    max_k: int = 0  # 0: every k of the trace; else no more than this are looked for
    rule: str = "argmin"  # argmin, knee
    #: Which gap counts for k clusters: the largest on the way to them (formed),
    #: or that of the next merge, the literal minimum over their pairs (next).
    theta: str = "formed"
    k: int = 0  # 0: chosen from the trace
    carry: str = "cold"  # cold, warm
    prune: str = "off"  # off, idle
    min_hits: int = 1
    idle_chunks: int = 3
    max_rows_per_task: int = 200_000

    def __post_init__(self):
        if self.subnets < 1 or self.rho < 1 or self.s < 1 or not 0 < self.lr_win <= 1 or not 0 <= self.lr_nbr <= 1 or not 0 <= self.decay < 1:
            raise ValueError("parameter out of range")
        for name, allowed in (("seeding", ("poisson", "random", "farthest", "given")), ("schedule", ("guided", "two_stage", "adjacent", "all_pairs", "none")), ("separability", ("object", "neuron")), ("rule", ("argmin", "knee")), ("theta", ("formed", "next")), ("carry", ("cold", "warm")), ("prune", ("off", "idle"))):
            if getattr(self, name) not in allowed:
                raise ValueError(f"{name} must be one of {allowed}")
