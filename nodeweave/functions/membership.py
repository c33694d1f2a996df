"""Node membership of variables: the multiplicative rule and the guards around it."""

from __future__ import annotations

import numpy as np

from .numeric import signed_parts, unit_columns

MOMENT_MODES = ("signed", "absolute", "sign_split")
UPDATES = ("multiplicative", "disjoint", "hard", "frozen")


def ortho_multiplier(w, a, omega):
    """Multiplier of the orthonormality constraint, k x k."""
    return -(w.T @ a @ w) @ omega


def ratio_terms(w, a, omega, moment_mode="sign_split"):
    """Numerator and denominator of the rule; both non-negative except under ``signed``."""
    up, down = signed_parts(omega)
    if moment_mode == "absolute":
        a = np.abs(a)
    plus, minus = signed_parts(ortho_multiplier(w, a, omega))
    if moment_mode == "sign_split":
        ap, an = signed_parts(a)
        pw, nw = ap @ w, an @ w
        return pw @ down + nw @ up + w @ minus, pw @ up + nw @ down + w @ plus
    if moment_mode in ("signed", "absolute"):
        aw = a @ w
        return aw @ down + w @ minus, aw @ up + w @ plus
    raise ValueError(f"moment_mode must be one of {MOMENT_MODES}")


def ratio_from_product(w, aw, omega):
    """The same from the product A W alone (signed moments)."""
    up, down = signed_parts(omega)
    plus, minus = signed_parts(-(w.T @ aw) @ omega)
    return aw @ down + w @ minus, aw @ up + w @ plus


def apply_ratio(w, numerator, denominator, normalize=True, floor=1e-10):
    """W times the ratio, elementwise; entries at zero stay there. Unit columns by default, as the scale is free."""
    new = w * np.maximum(numerator, floor) / np.maximum(denominator, floor)
    return unit_columns(new) if normalize else new


def update_membership(w, a, omega, moment_mode="sign_split", normalize=True, floor=1e-10):
    """One multiplicative step."""
    return apply_ratio(w, *ratio_terms(w, a, omega, moment_mode), normalize, floor)


def disjoint(w):
    """Keep each variable's largest weight; unit columns are then orthonormal and non-negative."""
    out = np.zeros_like(w)
    rows = np.arange(len(w))
    best = w.argmax(axis=1)
    out[rows, best] = w[rows, best]
    return unit_columns(out)


def hard(w):
    """Indicators of each variable's largest weight, unit columns."""
    out = np.zeros_like(w)
    out[np.arange(len(w)), w.argmax(axis=1)] = 1.0
    return unit_columns(out)


def residual_variance(a_trace, wtaw, gram, p):
    """Mean variance outside the span of W, from tr A, W'AW and W'W; floored."""
    k = len(gram)
    if p <= k:
        return 1.0
    inside = float(np.trace(np.linalg.solve(gram + 1e-12 * np.eye(k), wtaw)))
    return max((a_trace - inside) / (p - k), 1e-6 * max(a_trace / p, 1e-12))
