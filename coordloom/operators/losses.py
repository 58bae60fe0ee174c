"""Losses: value, conjugate and the exact coordinate step, for numpy arrays and (ridge, hinge) as columns.

Written for labels y, margin z = x.w, dual value alpha (b = y alpha), s = sigma q / (lam n) with q = |x|^2.
"""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

LOSSES = ("logistic", "ridge", "hinge", "squared_hinge", "smooth_hinge")
GAMMA = 0.5  # smoothing of smooth_hinge
NEWTON_STEPS = 80


def _sigmoid(u):
    return 1.0 / (1.0 + np.exp(-np.clip(u, -700, 700)))


def logit_root(c, s, b):
    """u with u + c + s (sigmoid(u) - b) = 0.

    The left side rises with slope 1 or more and the root lies between -c - s (1 - b) and -c + s b; a Newton step that
    leaves what is left of that interval, or isn't half as long as the step before, goes to its middle instead (for large s plain Newton can swing between two points).
    """
    c, s, b = (np.asarray(x, dtype=float) for x in (c, s, b))
    low, high, u = -c - s * (1.0 - b), -c + s * b, -c * np.ones_like(s * b)
    last = np.inf
    for _ in range(NEWTON_STEPS):
        p = _sigmoid(u)
        g = u + c + s * (p - b)
        low, high = np.where(g < 0, u, low), np.where(g > 0, u, high)
        move = np.abs(g / (1.0 + s * p * (1.0 - p)))
        new = u - np.sign(g) * move
        stuck = (move > 0.5 * last) & (move > 1e-12 * (1.0 + np.abs(u)))
        new = np.where(stuck | (new < low) | (new > high), 0.5 * (low + high), new)
        last = np.abs(new - u)
        if np.all(np.abs(new - u) <= 1e-15 * (1.0 + np.abs(new))):
            return new
        u = new
    return u


def step(loss: str, z, q, y, alpha, s):
    """The change of alpha that minimises the coordinate's objective."""
    if loss == "ridge":
        return (y - z - alpha) / (1.0 + s)
    b = y * alpha
    if loss == "logistic":
        return y * (_sigmoid(logit_root(y * z, s, b)) - b)
    if loss == "hinge":
        safe = np.where(np.asarray(s) > 0, s, 1.0)
        new = np.where(np.asarray(s) > 0, np.clip(b + (1.0 - y * z) / safe, 0.0, 1.0), 1.0)
    elif loss == "squared_hinge":
        new = np.maximum(0.0, (1.0 - y * z + s * b) / (s + 0.5))
    elif loss == "smooth_hinge":
        new = np.clip((1.0 - y * z + s * b) / (s + GAMMA), 0.0, 1.0)
    else:
        raise ValueError(f"unknown loss {loss!r}")
    return y * (new - b)


def scalar_root(c: float, s: float, b: float) -> float:
    """``logit_root`` for plain floats: the same interval and the same safeguard."""
    low, high, u, last = -c - s * (1.0 - b), -c + s * b, -c, math.inf
    for _ in range(NEWTON_STEPS):
        p = 1.0 / (1.0 + math.exp(-u)) if u > -700.0 else 0.0
        g = u + c + s * (p - b)
        if g < 0:
            low = u
        elif g > 0:
            high = u
        move = g / (1.0 + s * p * (1.0 - p))
        new, size = u - move, abs(move)
        near = 1e-14 * (1.0 + abs(u))
        if size <= near:
            return new
        if new < low or new > high or size > 0.5 * last:
            new = 0.5 * (low + high)
        last, u = abs(new - u), new
    return u


def scalar_step(loss: str):
    """``step`` for plain floats: (z, q, y, alpha, s) to the change of alpha."""
    if loss == "ridge":
        return lambda z, q, y, a, s: (y - z - a) / (1.0 + s)
    if loss == "logistic":

        def logistic(z: float, q: float, y: float, a: float, s: float) -> float:
            b = y * a
            u = scalar_root(y * z, s, b)
            return y * ((1.0 / (1.0 + math.exp(-u)) if u > -700.0 else 0.0) - b)

        return logistic
    if loss == "hinge":
        return lambda z, q, y, a, s: y * ((min(1.0, max(0.0, y * a + (1.0 - y * z) / s)) if s > 0 else 1.0) - y * a)
    if loss == "squared_hinge":
        return lambda z, q, y, a, s: y * (max(0.0, (1.0 - y * z + s * y * a) / (s + 0.5)) - y * a)
    if loss == "smooth_hinge":
        return lambda z, q, y, a, s: y * (min(1.0, max(0.0, (1.0 - y * z + s * y * a) / (s + GAMMA))) - y * a)
    raise ValueError(f"unknown loss {loss!r}")


def value(loss: str, z, y):
    m = y * z
    if loss == "ridge":
        return 0.5 * (z - y) ** 2
    if loss == "logistic":
        return np.maximum(-m, 0.0) + np.log1p(np.exp(-np.abs(m)))
    if loss == "hinge":
        return np.maximum(0.0, 1.0 - m)
    if loss == "squared_hinge":
        return np.maximum(0.0, 1.0 - m) ** 2
    return np.where(m >= 1, 0.0, np.where(m <= 1 - GAMMA, 1 - m - GAMMA / 2, (1 - m) ** 2 / (2 * GAMMA)))


def conjugate(loss: str, y, alpha):
    """phi*(-alpha)."""
    b = y * alpha
    if loss == "ridge":
        return 0.5 * alpha**2 - alpha * y
    if loss == "logistic":
        b = np.clip(b, 0.0, 1.0)
        with np.errstate(divide="ignore", invalid="ignore"):
            return np.where(b > 0, b * np.log(np.where(b > 0, b, 1)), 0.0) + np.where(b < 1, (1 - b) * np.log1p(-np.where(b < 1, b, 0)), 0.0)
    if loss == "hinge":
        return -b
    if loss == "squared_hinge":
        return -b + b**2 / 4
    return -b + GAMMA * b**2 / 2


def slope(loss: str, z, y):
    """Derivative of the loss by the margin z."""
    m = y * z
    if loss == "ridge":
        return z - y
    if loss == "logistic":
        return -y * _sigmoid(-m)
    if loss == "hinge":
        return np.where(m < 1, -y, 0.0)
    if loss == "squared_hinge":
        return np.where(m < 1, -2 * y * (1 - m), 0.0)
    return np.where(m >= 1, 0.0, np.where(m <= 1 - GAMMA, -y, -y * (1 - m) / GAMMA))


def curvature(loss: str, z, y):
    """Second derivative by the margin (smooth losses)."""
    if loss == "ridge":
        return np.ones_like(z)
    if loss == "logistic":
        p = _sigmoid(z)
        return p * (1 - p)
    raise ValueError(f"no second derivative for {loss!r}")


def step_expr(loss: str, z: Column, q: Column, y: Column, alpha: Column, s: Column) -> Column:
    """The same step as a column, for the losses with a closed form."""
    b = y * alpha
    if loss == "ridge":
        return (y - z - alpha) / (1 + s)
    if loss == "hinge":
        new = F.when(s > 0, F.greatest(F.lit(0.0), F.least(F.lit(1.0), b + (1 - y * z) / s))).otherwise(F.lit(1.0))
    elif loss == "squared_hinge":
        new = F.greatest(F.lit(0.0), (1 - y * z + s * b) / (s + 0.5))
    elif loss == "smooth_hinge":
        new = F.greatest(F.lit(0.0), F.least(F.lit(1.0), (1 - y * z + s * b) / (s + GAMMA)))
    else:
        raise ValueError(f"no closed form for {loss!r}")
    return y * (new - b)


def logloss_expr(margin: Column) -> Column:
    """ln(1 + exp(-m)) without overflow."""
    return F.greatest(-margin, F.lit(0.0)) + F.log1p(F.exp(-F.abs(margin)))
