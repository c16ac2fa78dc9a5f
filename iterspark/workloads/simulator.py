"""Draws edits as developers make them: a phase by weight, then one of the workload's edits of that phase."""

from __future__ import annotations

import random

#: Our defaults; the weights are parameters.
WEIGHTS = {"price_class": {"prep": 0.3, "learn": 0.1, "post": 0.6}, "entity_clusters": {"prep": 0.3, "learn": 0.4, "post": 0.3}, "pair_extraction": {"prep": 1.0}, "digit_vectors": {"prep": 0.2, "learn": 0.4, "post": 0.4}}


def simulate(edits: list[tuple[str, dict]], weights: dict[str, float], iterations: int, seed: int) -> list[tuple[str, dict]]:
    rng = random.Random(seed)
    by_phase: dict[str, list[dict]] = {}
    for phase, change in edits[1:]:
        by_phase.setdefault(phase, []).append(change)
    phases = [p for p in weights if p in by_phase]
    out = []
    for _ in range(iterations):
        phase = rng.choices(phases, [weights[p] for p in phases])[0]
        out.append((phase, rng.choice(by_phase[phase])))
    return out
