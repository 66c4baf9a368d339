"""Parameters of a synthesis run."""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class SynthParams:
    theta: float = 0.95
    coherence_min: float | None = None
    f_ed: tuple[int, int] = (1, 5)
    k_ed: int = 10
    theta_overlap: int = 0
    theta_edge: float = 0.85
    tau: float = -0.2
    use_negative: bool = True
    neg_update: str = "min"
    #: Components of more edges than this are merged in distributed rounds, others each in one task.
    task_edges: int = 2_000_000
