"""The serial kernel: one sample after another finds its winner and pulls the winner's neighbourhood."""

from __future__ import annotations

import time
from collections.abc import Callable, Iterable
from dataclasses import dataclass, field

import numpy as np

from ..config import MapConfig
from .grid import init_gradient, init_random
from .ordering import order_of, start_index
from .schedule import radius_at, rate_at, weights_at


@dataclass
class FoldState:
    prototypes: np.ndarray
    winners: np.ndarray
    history: list[dict] = field(default_factory=list)
    stop_reason: str = ""


def start_prototypes(cfg: MapConfig, dim: int, given: np.ndarray | None = None) -> np.ndarray:
    if cfg.init == "given":
        return np.array(given, dtype=np.float64)
    return init_gradient(cfg.rows, cfg.cols, dim) if cfg.init == "gradient" else init_random(cfg.rows, cfg.cols, dim, cfg.seed)


def show(prototypes: np.ndarray, x: np.ndarray, order: Iterable[int], weights: np.ndarray | Callable[[int], np.ndarray], winners: np.ndarray) -> int:
    """Shows the rows of ``x`` in the given order; changes prototypes and winners in place; gives the number of changed winners."""
    moves = 0
    at_step = weights if callable(weights) else None
    for step, i in enumerate(order):
        gap = x[i] - prototypes
        # cumsum adds from left to right, as the SQL twins do; argmin takes the first of equals
        winner = int(np.cumsum(gap * gap, axis=1)[:, -1].argmin())
        w = (at_step(step) if at_step else weights)[winner]
        prototypes += w[:, None] * gap
        if winners[i] != winner:
            winners[i] = winner
            moves += 1
    return moves


def fold_map(x: np.ndarray, cfg: MapConfig, given: np.ndarray | None = None) -> FoldState:
    """All passes over the rows of ``x``, which stand in the order of the training list."""
    n = len(x)
    if not n:
        raise ValueError("an empty training list has no map")
    cfg = cfg.resolved(n)
    state = FoldState(start_prototypes(cfg, x.shape[1], given), np.full(n, -1, np.int64))
    for t in range(cfg.max_passes):
        began = time.perf_counter()
        moves = show(state.prototypes, x, order_of(cfg.selection, n, t, cfg.seed), pass_weights(cfg, t, n), state.winners)
        if cfg.moves == "frozen":
            from .distance import nearest_two

            frozen = nearest_two(x, state.prototypes)[0]
            last = state.__dict__.get("frozen", np.full(n, -1))
            moves, state.__dict__["frozen"] = int((frozen != last).sum()), frozen
        state.history.append(history_row(cfg, t, n, moves, time.perf_counter() - began))
        if cfg.stop == "no_moves" and t > 0 and moves == 0:
            state.stop_reason = "no_moves"
            return state
    state.stop_reason = "horizon" if cfg.max_passes == cfg.horizon else "max_passes"
    return state


def pass_weights(cfg: MapConfig, t: int, n: int):
    """Weights of pass ``t``; with the per-sample clock a function of the step."""
    at = lambda clock, horizon: weights_at(clock, horizon, cfg.rows, cfg.cols, cfg.initial_rate, cfg.base, cfg.neighbourhood)
    if cfg.clock == "sample":
        return lambda step: at(t * n + step, cfg.horizon * n)
    return at(t, cfg.horizon)


def history_row(cfg: MapConfig, t: int, n: int, moves: int, seconds: float) -> dict:
    staggered = cfg.selection == "staggered"
    return {
        "pass": t,
        "start_index": start_index(t, n) if staggered else int(order_of(cfg.selection, n, t, cfg.seed)[0]),
        "direction": "backward" if staggered and t % 2 else "forward",
        "radius": radius_at(t, cfg.horizon, min(cfg.rows, cfg.cols) / 2),
        "rate": rate_at(t, cfg.horizon, cfg.initial_rate, cfg.base),
        "moves": moves,
        "seconds": seconds,
    }


def fold_samples(x: np.ndarray, state, step: Callable, *, selection: str = "staggered", seed: int | None = None, passes: int = 1, stop: Callable | None = None):
    """The order and the stop as devices for any learner: ``step(state, row, index, t)`` gives the next state."""
    for t in range(passes):
        for i in order_of(selection, len(x), t, seed):
            state = step(state, x[i], int(i), t)
        if stop is not None and stop(state, t):
            break
    return state
