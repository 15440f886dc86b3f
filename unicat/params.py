"""All settings of the categorisation methods, with the defaults that the experiments use."""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class Params:
    # Representation
    words_s: int = 500  # structural words
    words_t: int = 500  # texture words
    patch: int = 8
    stride: int = 8
    saturation: float = 2.0  # s of the zero-anchored sigmoid
    # Graph
    eps: float = 1e-2  # smoothing of responses before they are normalised
    tau: float = 0.2
    q_min: float = 1e-3
    q_cap: float = 1 - 1e-9  # of equal items, so that log(1 - q) stays finite
    neighbours: int = 6
    knn_mode: str = "union"  # union, mutual or capped
    # Posterior and category models
    beta: float = 300.0
    beta_mode: str = "absolute"  # or per_item: beta * N / beta_items
    beta_items: int = 1000
    model_words: int = 40  # T
    rule: str = "mean_gap"  # or kl_gain
    clip: float = 1e-6
    # Sampler
    move: str = "composite"  # or single
    scope: str = "same_label"  # or any
    fidelity: str = "reversible"  # or paper: printed ratio, label-set correction dropped, joint acceptance
    cp_scale: float = 1.0
    p_pick: float = 0.3
    steps: int = 2000
    patience: int = 300
    seed: int = 42
    initial: str = "one"  # one, components, singletons or random

    def beta_for(self, items: int) -> float:
        return self.beta if self.beta_mode == "absolute" else self.beta * items / self.beta_items
