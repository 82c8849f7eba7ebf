"""Choosing the number of resamples and the sample size before the big run, from a small pilot on the driver."""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass, field

import numpy as np

from approxboot.functions.accuracy import z_value
from approxboot.operators.maintain import maintain_plain

Statistic = Callable[[np.ndarray], float]


@dataclass
class Plan:
    """mode: early (sample of n, B resamples) or exact; message says why; trace and curve are the planner's steps."""

    B: int
    n: int
    p: float
    mode: str
    message: str
    trace: list = field(default_factory=list)
    curve: dict = field(default_factory=dict)


def replicate(values: np.ndarray, f: Statistic, replicates: int, gen: np.random.Generator) -> np.ndarray:
    n = len(values)
    return np.array([f(values[gen.integers(0, n, n)]) for _ in range(replicates)])


def cv_of(thetas: np.ndarray) -> float:
    m = abs(thetas.mean())
    return float(thetas.std() / m) if m else math.inf


def plan_B(pilot: np.ndarray, f: Statistic, tau: float, rule: str = "rel", b_min: int | None = None, patience: int | None = None, seed: int = 0) -> tuple[int, list[tuple[int, float]]]:
    """Fewest resamples at which the error estimate is stable; one new resample per step.

    abs: the estimate changes by less than tau once. rel: by less than tau of itself, patience times in a
    row, and not below b_min resamples, since a change in absolute terms is small from the start for a
    precise statistic. Up to 1 / tau (b_min at least) resamples are tried.
    """
    b_min = b_min if b_min is not None else (2 if rule == "abs" else 30)
    patience = patience if patience is not None else (1 if rule == "abs" else 3)
    gen = np.random.Generator(np.random.PCG64(seed))
    most = max(b_min, math.ceil(1 / tau))
    thetas = list(replicate(pilot, f, 2, gen))
    trace, still, before = [(2, cv_of(np.array(thetas)))], 0, None
    for b in range(3, most + 1):
        thetas.append(replicate(pilot, f, 1, gen)[0])
        before, now = trace[-1][1], cv_of(np.array(thetas))
        trace.append((b, now))
        still = still + 1 if abs(now - before) < (tau if rule == "abs" else tau * now) else 0
        if still >= patience and b >= b_min:
            return b, trace
    return most, trace


def subsample_sizes(n: int, levels: int = 5, least: int = 0) -> list[float]:
    """Nested sizes n / 2**(levels - i); those below least are left out."""
    return [s for i in range(1, levels + 1) if (s := n / 2 ** (levels - i)) >= least]


def fit_curve(sizes: list[float], cvs: list[float], model: str = "power") -> dict:
    """Least-squares curve of c_v over n, weighted by size: power a * n**k, invsqrt a / sqrt(n), invsqrt_c with a constant."""
    x, y = np.asarray(sizes, float), np.asarray(cvs, float)
    w = np.sqrt(x)
    if model == "power":
        m = np.column_stack([np.ones(len(x)), np.log(x)]) * w[:, None]
        (a, k), *_ = np.linalg.lstsq(m, np.log(np.maximum(y, 1e-300)) * w, rcond=None)
        return {"model": model, "a": float(np.exp(a)), "k": float(k), "c": 0.0}
    m = np.column_stack([x**-0.5] + ([np.ones(len(x))] if model == "invsqrt_c" else [])) * w[:, None]
    fit, *_ = np.linalg.lstsq(m, y * w, rcond=None)
    return {"model": model, "a": float(fit[0]), "k": -0.5, "c": float(fit[1]) if model == "invsqrt_c" else 0.0}


def invert_curve(curve: dict, sigma: float) -> float:
    """Size at which the curve meets sigma; infinite where it does not."""
    room = sigma - curve["c"]
    if room <= 0 or curve["a"] <= 0:
        return math.inf if curve["a"] > 0 else 1.0
    if curve["k"] >= 0:
        return math.inf
    return (room / curve["a"]) ** (1 / curve["k"])


def plan_n(pilot: np.ndarray, f: Statistic, B: int, sigma: float, tau: float, levels: int = 5, model: str = "power", seed: int = 0, least: int = 8) -> tuple[int, dict]:
    """Sample size for c_v <= sigma from nested subsamples of the first 1 / tau pilot values (more, where levels would be too small).

    Resamples are drawn for the smallest subsample and maintained from one to the next; touched counts the items
    that were drawn or taken out on the way.
    """
    n0 = min(len(pilot), max(math.ceil(1 / tau), least * 2 ** (levels - 1)))
    sizes = [int(s) for s in subsample_sizes(n0, levels, least)] or [n0]
    gen = np.random.Generator(np.random.PCG64([seed, 1]))
    held = [pilot[: sizes[0]][gen.integers(0, sizes[0], sizes[0])] for _ in range(B)]
    touched, cvs = B * sizes[0], [cv_of(np.array([f(r) for r in held]))]
    for before, s in zip(sizes, sizes[1:]):
        grown = [maintain_plain(r, pilot[:before], pilot[before:s], seed + s, b) for b, r in enumerate(held)]
        held, touched = [r for r, _ in grown], touched + sum(n for _, n in grown)
        cvs.append(cv_of(np.array([f(r) for r in held])))
    if max(cvs) == 0:
        return sizes[0], {"model": "constant", "sizes": sizes, "cvs": cvs, "a": 0.0, "k": -0.5, "c": 0.0}
    curve = fit_curve(sizes, cvs, model) if len(sizes) > 1 else {"model": "invsqrt", "a": cvs[0] * math.sqrt(sizes[0]), "k": -0.5, "c": 0.0}
    curve |= {"sizes": sizes, "cvs": cvs, "touched": touched}
    n = invert_curve(curve, sigma)
    return (int(math.ceil(n)) if math.isfinite(n) else 1 << 62), curve


def theory_B(eps0: float) -> int:
    """Resamples for a relative Monte-Carlo error eps0 of the error estimate."""
    return max(1, math.ceil(0.5 / eps0**2 - 1e-9))


def theory_n(cv_pop: float, sigma: float, z: float = 1.0, N: int | None = None) -> int:
    """Sample size at which the mean's relative standard error (z of them) is sigma; N corrects for a finite population."""
    n = (z * cv_pop / sigma) ** 2
    if N:
        n = n / (1 + n / N)
    return max(1, math.ceil(n - 1e-9))


def feasible(B: int, n: int, N: int, costs: tuple[float, float] | None = None) -> tuple[bool, str]:
    """Whether an early answer is worth it: B * n < N, or with costs (scan, resample) a row, the cheaper of the two."""
    if costs:
        early, exact = costs[0] * n + costs[1] * B * n, costs[0] * N
        return early < exact, f"early costs {early:g}, exact {exact:g}"
    if B * n < N:
        return True, f"{B} resamples of {n} rows are fewer than {N} rows"
    return False, f"an early answer is no faster: {B} resamples of {n} rows against {N} rows"


def plan(pilot: np.ndarray, f: Statistic, N: int, sigma: float, tau: float = 0.01, confidence: float | None = None, rule: str = "rel", model: str = "power", costs: tuple[float, float] | None = None, seed: int = 0) -> Plan:
    """Both phases on the driver: B, then n, then whether it pays. confidence asks for z * c_v <= sigma."""
    if sigma <= 0:
        raise ValueError("sigma must be positive")
    if len(pilot) < 2:
        return Plan(0, N, 1.0, "exact", "the pilot has fewer than two values")
    goal = sigma / z_value(confidence) if confidence else sigma
    B, trace = plan_B(pilot, f, tau, rule, seed=seed)
    n, curve = plan_n(pilot, f, B, goal, tau, model=model, seed=seed)
    ok, message = feasible(B, n, N, costs)
    return Plan(B, n, min(1.0, n / N) if N else 1.0, "early" if ok else "exact", message, trace, curve)


def plan_doubling(sample: np.ndarray, f: Statistic, sigma: float, n0: int = 16, B0: int = 8, seed: int = 0) -> list[tuple[int, int, float]]:
    """Baseline: run, and double n (and B up to 64) while the error is above sigma: (n, B, c_v) of every run."""
    gen = np.random.Generator(np.random.PCG64([seed, 2]))
    n, B, out = n0, B0, []
    while True:
        n = min(n, len(sample))
        out.append((n, B, cv_of(replicate(sample[:n], f, B, gen))))
        if out[-1][2] <= sigma or n == len(sample):
            return out
        n, B = 2 * n, min(64, 2 * B)
