"""All parameters of the loop in one frozen record."""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class LoopConfig:
    # given by the reference
    retrieve_k: int = 30
    windows: int = 3
    # our values where it names a threshold without one
    theta_relation: int = 5
    theta_event: int = 5
    coherence_min: float = 0.60
    entity_sim_min: float = 0.80
    event_sim_min: float = 0.75
    reuse_min: float = 0.85
    profile_top: int = 5
    event_time_slack_seconds: int = 3600
    review_heads: int = 3
    review_type_share: float = 0.8
    # switches of the ablations
    intent: bool = True
    events: bool = True
    coref: bool = True
    guidance: bool = True
    logic: bool = True
    evidence: bool = True

    def guided(self, k: int) -> bool:
        """Schemas, history and cross-batch alignment are used from the second batch on."""
        return k > 0
