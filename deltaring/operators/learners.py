"""More learners that need no more than maintained moments."""

from __future__ import annotations

import math
from itertools import combinations_with_replacement

import numpy as np

from .ridge import Moments


def residual(m: Moments, chosen: list[int]) -> float:
    """Mean squared error of the best linear model on some columns (the constant always in)."""
    cols = [0, *chosen]
    a, b = m.matrix[np.ix_(cols, cols)], m.matrix[cols, -1]
    theta = np.linalg.lstsq(a, b, rcond=None)[0]
    return max(float(m.matrix[-1, -1] - 2 * theta @ b + theta @ a @ theta), 0.0)


def stepwise(m: Moments, direction: str = "forward") -> list[tuple[int, str, float, float]]:
    """(step, attribute, mse, aic) in the order attributes were added or dropped; stops when AIC no longer falls.

    One-hot columns of an attribute go together. Only blocks of the moment matrix are solved.
    """
    groups: dict[str, list[int]] = {}
    for i, (attr, _) in enumerate(m.names[1:-1], 1):
        groups.setdefault(attr, []).append(i)

    def aic(mse: float, k: int) -> float:
        return m.n * math.log(max(mse, 1e-300)) + 2 * k

    def cost(names: set[str]) -> tuple[float, float]:
        cols = [i for g in sorted(names) for i in groups[g]]
        mse = residual(m, cols)
        return mse, aic(mse, len(cols) + 1)

    inside = set() if direction == "forward" else set(groups)
    now, out = cost(inside)[1], []
    while True:
        moves = sorted(set(groups) - inside if direction == "forward" else inside)
        tried = [(*cost(inside | {g} if direction == "forward" else inside - {g}), g) for g in moves]
        if not tried:
            return out
        mse, best, g = min(tried, key=lambda t: (t[1], t[2]))
        if best >= now - 1e-9:
            return out
        inside = inside | {g} if direction == "forward" else inside - {g}
        now = best
        out.append((len(out) + 1, g, mse, best))


def poly_features(names: list[str], degree: int) -> list[tuple[str, ...]]:
    """Monomials of some attributes up to a degree, the constant first."""
    return [m for d in range(degree + 1) for m in combinations_with_replacement(sorted(names), d)]


def poly_moments(terms: dict[tuple[str, ...], float], names: list[str], label: str, degree: int) -> Moments:
    """Moments of all monomials up to a degree and the label, from moments of twice the degree (term -> value)."""
    features = [f for f in poly_features([n for n in names if n != label], degree)]
    columns = [*features, (label,)]
    n = terms[()]
    at = lambda a, b: terms.get(tuple(sorted(a + b)), 0.0) / n
    return Moments(n, [("*".join(f) or "1", None) for f in columns], np.array([[at(a, b) for b in columns] for a in columns]))


def term_values(rows) -> dict[tuple[str, ...], float]:
    """Collected rows (term, v) of a sparse root over continuous attributes."""
    return {tuple(f["a"] for f in r["term"]): float(r["v"]) for r in rows}


def fm_loss_gradient(terms: dict[tuple[str, ...], float], names: list[str], label: str, w0: float, w: np.ndarray, v: np.ndarray) -> tuple[float, float, np.ndarray, np.ndarray]:
    """Half the mean squared error of a factorisation machine and its gradient, from moments up to degree 4."""
    x, n = list(names), terms[()]
    e = lambda *t: terms.get(tuple(sorted(t)), 0.0) / n
    pairs = [(i, j) for i in range(len(x)) for j in range(i + 1, len(x))]
    poly = {(): w0}
    for i, a in enumerate(x):
        poly[(a,)] = w[i]
    for i, j in pairs:
        poly[(x[i], x[j])] = float(v[i] @ v[j])
    err = {**poly, (label,): poly.get((label,), 0.0) - 1.0}
    mean_with = lambda t: sum(c * e(*k, *t) for k, c in err.items())
    loss = 0.5 * sum(c * mean_with(k) for k, c in err.items())
    g0, gw, gv = mean_with(()), np.array([mean_with((a,)) for a in x]), np.zeros_like(v)
    for i, j in pairs:
        g = mean_with((x[i], x[j]))
        gv[i] += g * v[j]
        gv[j] += g * v[i]
    return loss, g0, gw, gv


def fm_fit(terms: dict[tuple[str, ...], float], names: list[str], label: str, rank: int = 2, steps: int = 500, seed: int = 0) -> tuple[float, np.ndarray, np.ndarray, list[float]]:
    """w0, w, v and the loss after each step, by descent with a step that grows while the loss falls and is halved when not."""
    r = np.random.default_rng(seed)
    w0, w, v, rate, losses = 0.0, np.zeros(len(names)), r.normal(0, 0.1, (len(names), rank)), 0.1, []
    loss, g0, gw, gv = fm_loss_gradient(terms, names, label, w0, w, v)
    for _ in range(steps):
        losses.append(loss)
        while rate > 1e-14:
            trial = (w0 - rate * g0, w - rate * gw, v - rate * gv)
            new = fm_loss_gradient(terms, names, label, *trial)
            if new[0] < loss:
                (w0, w, v), (loss, g0, gw, gv) = trial, new
                rate *= 1.5
                break
            rate /= 2
        else:
            break
    losses.append(loss)
    return w0, w, v, losses
