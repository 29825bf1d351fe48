"""Model configuration, the presets of the experiments and the ablation variants."""

from __future__ import annotations

from dataclasses import dataclass, replace


@dataclass(frozen=True)
class ModelConfig:
    n: int
    w: int
    k: int
    d: int = 128
    ratio: float = 0.8
    structure: str = "uniform"  # uniform, pair, irregular
    symmetry: str = "none"  # none, union, mutual
    position: str = "learned"  # learned, neighbourhood, none, sinusoidal
    use_z: bool = True
    attention: bool = True
    score: str = "softmax"  # softmax, projection
    gate: bool = True
    skip: str = "add"  # add, fill, none
    shift: str = "difference"  # difference, dot
    head: str = "forecast"  # forecast, classify
    hidden: tuple[int, ...] = ()
    smooth: str = "trailing"  # trailing, printed
    w_a: int = 10
    robust_on: str = "validation"  # validation, self
    eps: float = 1e-6
    rewrites: bool = True
    temperature: float = 0.2
    seed: int = 1

    def capped(self) -> ModelConfig:
        return replace(self, k=min(self.k, self.n - 1))


#: panel, n, w, k of the six experiment sets, and whether detection is adjusted by segments
PRESETS = {
    "plant": ("brand_status", 51, 30, 15, True),
    "network": ("nation_segment", 123, 30, 25, True),
    "telemetry25": ("nation_ship", 25, 60, 7, False),
    "telemetry50": ("user_cohort", 55, 60, 10, False),
    "simulator": ("size_flow", 52, 30, 20, False),
    "testbed": ("axis", 59, 25, 20, False),
}

ABLATIONS = {
    "pair_edges": {"structure": "pair", "k": 1},
    "irregular_edges": {"structure": "irregular"},
    "no_position": {"position": "none"},
    "sinusoidal_position": {"position": "sinusoidal"},
    "no_embedding": {"use_z": False},
    "no_attention": {"attention": False},
    "projection_score": {"score": "projection"},
    "no_gate": {"gate": False},
    "dot_shift": {"shift": "dot"},
}


def ablation(cfg: ModelConfig, name: str) -> ModelConfig:
    return replace(cfg, **ABLATIONS[name])
