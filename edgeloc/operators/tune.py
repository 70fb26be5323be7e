"""Search of thresholds and walk parameters: a tree-structured Parzen estimator, and a grid that checks it."""

from __future__ import annotations

import math
from collections.abc import Callable
from itertools import product

import numpy as np

Space = dict[str, tuple[float, float, str]]  # name: low, high, "lin" or "log"


def _density(x: np.ndarray, centres: np.ndarray, low: float, high: float) -> np.ndarray:
    width = max((high - low) / max(1, len(centres)) ** 0.5, 1e-12) / 2
    return np.exp(-0.5 * ((x[:, None] - centres) / width) ** 2).sum(1) / width + 1 / (high - low)


def tpe(objective: Callable[[list[dict[str, float]]], list[float]], space: Space, trials: int = 32, batch: int = 8, gamma: float = 0.25, seed: int = 1, tries: int = 24) -> list[tuple[dict[str, float], float]]:
    """Trials in order; a larger value is better. A batch is judged in one call, so one job serves it: the first at random, then of some draws near good trials those likeliest to be good."""
    rng, done = np.random.default_rng(seed), []
    to = {k: (math.log(a), math.log(b)) if how == "log" else (a, b) for k, (a, b, how) in space.items()}
    plain = lambda x: {k: math.exp(v) if space[k][2] == "log" else float(v) for k, v in x.items()}

    while len(done) < trials:
        drawn = []
        ranked = sorted(done, key=lambda d: -d[1])
        cut = max(1, math.ceil(gamma * len(done)))
        for _ in range(min(batch, trials - len(done))):
            x = {}
            for k, (low, high) in to.items():
                if not done:
                    x[k] = rng.uniform(low, high)
                    continue
                good, bad = (np.array([d[0][k] for d in part]) for part in (ranked[:cut], ranked[cut:]))
                width = (high - low) / max(1, len(good)) ** 0.5 / 2
                draws = np.clip(rng.choice(good, tries) + rng.normal(0, width, tries), low, high)
                x[k] = float(draws[np.argmax(_density(draws, good, low, high) / _density(draws, bad, low, high))])
            drawn.append(x)
        done += zip(drawn, objective([plain(x) for x in drawn]))
    return [(plain(x), y) for x, y in done]


def grid(objective: Callable[[list[dict[str, float]]], list[float]], values: dict[str, list[float]]) -> list[tuple[dict[str, float], float]]:
    """All combinations, judged in one call."""
    names = list(values)
    points = [dict(zip(names, v)) for v in product(*(values[n] for n in names))]
    return list(zip(points, objective(points)))
