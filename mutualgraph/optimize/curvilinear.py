"""Minimisation under X'X = I by curvilinear steps, seen through small Gram matrices.

A step moves X along Y(t) = (I + t/2 A)^-1 (I - t/2 A) X with A = G X' - X G'. A has rank 2k at most, so Y(t) = Z R(t) with
Z = [X | G] and a 2k x k matrix R(t) from a 2k x 2k solve. Objective and slope then need only Z'Z, Z'LZ and the anchor
rows' Gram matrices: a line search costs no pass over users, however often it backtracks.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np


@dataclass(frozen=True)
class Settings:
    theta: float = 1.0
    alpha: float = 1.0
    beta: float = 1.0
    rho: float = 1e-4
    eta: float = 0.85
    shrink: float = 0.1
    tau: float = 1e-3
    tau_min: float = 1e-10
    tau_max: float = 1e10
    tol: float = 1e-5
    max_iter: int = 200
    max_backtracks: int = 30
    gradient: str = "tangent"  # or "euclidean": what successive differences the two-point step uses
    alternate: bool = False  # long two-point steps and half ones in turn
    schedule: str = "interleaved"  # or "block": one network to convergence, then the other
    discrepancy_scale: str = "volume"  # or "printed"
    refresh: int = 8  # steps after which the carried product LX is formed anew
    reset: bool = True  # lift the reference value to the objective before a step
    start: str = "objective"  # or "zero", as printed; then no step may ever pass, which max_backtracks ends


@dataclass
class Grams:
    """Of one network at one step: zz = Z'Z, zlz = Z'LZ, nn = (TZ)'(TZ), cross = (TZ)'B of the other network's anchor
    rows B (both times the root of the pair's factor; nn is a list if there are several pairs), other = |B'B|^2, and back = Xprev'[X | G], for the two-point step."""

    zz: np.ndarray
    zlz: np.ndarray
    nn: np.ndarray
    cross: np.ndarray
    other: float
    back: np.ndarray | None = None


@dataclass
class Search:
    """What a network carries from step to step."""

    c: float | None = None
    q: float = 1.0
    tau: float = 1e-3
    last: tuple | None = None
    steps: int = 0
    record: list = field(default_factory=list)


def objective(r: np.ndarray, g: Grams, weight: float, c0: float) -> float:
    """weight tr(Y'LY) + c0 |BB' - B_other B_other'|^2 of Y = Z r."""
    own = sum(((r.T @ nn @ r) ** 2).sum() for nn in (g.nn if isinstance(g.nn, list) else [g.nn]))
    return float(weight * np.trace(r.T @ g.zlz @ r) + c0 * (own + g.other - 2 * ((r.T @ g.cross) ** 2).sum()))


def curve(tau: float, g: Grams) -> np.ndarray:
    """R(tau)."""
    k = len(g.zz) // 2
    xx, xg, gg = g.zz[:k, :k], g.zz[:k, k:], g.zz[k:, k:]
    inner = np.block([[xg, xx], [-gg, -xg.T]])
    w = np.linalg.solve(np.eye(2 * k) + tau / 2 * inner, np.vstack([xx, -xg.T]))
    return np.vstack([np.eye(k) - tau * w[k:], -tau * w[:k]])


def slope(g: Grams) -> float:
    """Derivative of the objective along the curve at 0: -|A|^2 / 2."""
    k = len(g.zz) // 2
    xx, xg, gg = g.zz[:k, :k], g.zz[:k, k:], g.zz[k:, k:]
    return float(-(np.trace(gg @ xx) - np.trace(xg @ xg)))


def tangent_norm(g: Grams) -> float:
    return float(np.sqrt(max(-2 * slope(g), 0.0) / 2))


def two_point(g: Grams, s: Search, cfg: Settings) -> float:
    """Step from the last two points and gradients; the current step where there are none yet."""
    if s.last is None or g.back is None:
        return s.tau
    k = len(g.zz) // 2
    xx, xg = g.zz[:k, :k], g.zz[:k, k:]
    old, r = s.last  # the step before: its zz, and R
    first = np.vstack([np.eye(k), np.zeros((k, k))])
    move = r - first
    ss = np.trace(move.T @ old @ move)
    pick = np.vstack([np.zeros((k, k)), np.eye(k)])
    if cfg.gradient == "tangent":
        old_grad = pick @ old[:k, :k] - first @ old[:k, k:].T  # G X'X - X G'X of the step before, in its Z
        now_by_x = xg @ xx - xx @ xg.T  # X' of this step's tangent gradient
        now_by_old = g.back[:, k:] @ xx - g.back[:, :k] @ xg.T
    else:
        old_grad, now_by_x, now_by_old = pick, xg, g.back[:, k:]
    sy = np.trace(now_by_x) - np.trace(now_by_old) - np.trace(move.T @ old @ old_grad)
    if abs(sy) <= 1e-300:
        return s.tau
    step = ss / abs(sy)
    return float(step * 0.5 if cfg.alternate and s.steps % 2 else step)


def line_search(g: Grams, s: Search, weight: float, c0: float, cfg: Settings) -> tuple[np.ndarray, dict]:
    """R of the accepted step, and what happened. If none passes within the cap, R is "stay"."""
    k = len(g.zz) // 2
    stay = np.vstack([np.eye(k), np.zeros((k, k))])
    f0 = objective(stay, g, weight, c0)
    if s.c is None:
        s.c = f0 if cfg.start == "objective" else 0.0
    if cfg.reset and cfg.start == "objective":
        s.c = max(s.c, f0)
    tau = min(max(two_point(g, s, cfg), cfg.tau_min), cfg.tau_max)
    d, tried = slope(g), 0
    while True:
        r = curve(tau, g)
        f = objective(r, g, weight, c0)
        if np.isfinite(f) and f <= s.c + cfg.rho * tau * d:
            break
        tried += 1
        tau *= cfg.shrink
        if tried >= cfg.max_backtracks:
            r, f = stay, f0
            break
    accepted = tried < cfg.max_backtracks
    if accepted:
        q = cfg.eta * s.q + 1
        s.c = (cfg.eta * s.q * s.c + f) / q
        s.q = q
        s.tau = max(min(tau, cfg.tau_max), cfg.tau_min)
    s.last = (g.zz, r)
    s.steps += 1
    return r, {"f": f, "c": s.c, "q": s.q, "tau": tau, "backtracks": tried, "accepted": accepted, "grad_norm": tangent_norm(g)}


def run(problem, cfg: Settings) -> list[dict]:
    """Alternate the networks of `problem` until all have settled; the record of all steps.

    problem: count, weight(i), c0, grams(i) (also forms Z), advance(i, R), norm(i) (sum of absolute entries of X) and
    residual(i) (|X'X - I|). A network has settled when its tangent gradient is below tol, or the norm's relative change is.
    """
    searches = [Search(tau=cfg.tau) for _ in range(problem.count)]
    records: list[dict] = []
    settled = [False] * problem.count
    norms = [problem.norm(i) for i in range(problem.count)]

    def step(i: int, iteration: int) -> None:
        g = problem.grams(i)
        r, seen = line_search(g, searches[i], problem.weight(i), problem.c0, cfg)
        problem.advance(i, r)
        now = problem.norm(i)
        change = abs(now - norms[i]) / max(abs(norms[i]), 1e-300)
        norms[i] = now
        settled[i] = not seen["accepted"] or seen["grad_norm"] < cfg.tol or change < cfg.tol * 1e-2
        records.append({"net": i, "iter": iteration, "l1": now, **seen})

    if cfg.schedule == "block":
        n = 0
        for _ in range(10):
            moved = False
            for i in range(problem.count):
                settled[i] = False
                searches[i].c = None
                for _ in range(cfg.max_iter):
                    n += 1
                    step(i, n)
                    if settled[i]:
                        break
                    moved = True
                if n >= cfg.max_iter * problem.count:
                    return records
            if not moved:
                break
        return records
    for n in range(1, cfg.max_iter + 1):
        for i in range(problem.count):
            step(i, n)
        if all(settled):
            break
    return records
