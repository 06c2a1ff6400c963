"""Defaults of every method in one place."""

from __future__ import annotations

from dataclasses import dataclass, field


@dataclass(frozen=True)
class Config:
    candidates: int = 8  # answers drawn a sample
    subset_size: int = 800  # effective samples wanted a round
    rollouts: int = 8  # rollouts a sample in the iterative stage
    trajectories: int = 15  # plans a task
    judges: int = 5
    max_steps: int = 25
    easy_share: float = 0.2
    ema_beta: float = 0.8
    rate_floor: float = 1 / 64
    probe: int = 32
    r_max: int = 3
    batch_size: int = 64
    gamma: float = 0.95
    eps: float = 1e-6
    delta: float = 0.001
    clip: float = 0.2
    kl_weight: float = 0.01
    temperature: float = 1.2
    tasks_per_round: int = 40
    judge_trajectories: int = 500
    # Correctness thresholds by part type, easy types to hard types.
    thresholds: dict = field(default_factory=lambda: {"SMALL": 0.1, "ECONOMY": 0.2, "STANDARD": 0.3, "MEDIUM": 0.5, "LARGE": 0.7, "PROMO": 0.85})


DEFAULTS = Config()

# Half-open price bands, and synonyms of each verb by line number modulo three.
BANDS = [(0, 1000), (1000, 5000), (5000, 12000), (12000, 30000), (20000, 60000)]
SYNONYMS = {"A": ("pick up", "grab", "take"), "N": ("put", "place", "set down"), "R": ("open", "pull open", "unlatch")}
