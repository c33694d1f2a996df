"""Small numeric helpers shared by the estimators."""

from __future__ import annotations

import numpy as np


def signed_parts(m):
    """Positive and negative part, both non-negative: m = plus - minus."""
    return np.maximum(m, 0.0), np.maximum(-m, 0.0)


def soft_threshold(m, t):
    return np.sign(m) * np.maximum(np.abs(m) - t, 0.0)


def log_sum_exp(z, axis=-1):
    top = z.max(axis=axis, keepdims=True)
    return np.squeeze(top, axis=axis) + np.log(np.exp(z - top).sum(axis=axis))


def symmetric(m):
    return (m + m.T) / 2


def safe_logdet(m, jitter=1e-10):
    """log det of a symmetric matrix with its eigenvalues floored."""
    return float(np.log(np.maximum(np.linalg.eigvalsh(symmetric(m)), jitter)).sum())


def psd_clip(m, floor=0.0):
    values, vectors = np.linalg.eigh(symmetric(m))
    return (vectors * np.maximum(values, floor)) @ vectors.T


def unit_columns(w, eps=1e-12):
    return w / np.maximum(np.linalg.norm(w, axis=0, keepdims=True), eps)


def max_overlap(w):
    """Largest cosine between two columns (0 for one column)."""
    u = unit_columns(w)
    c = u.T @ u
    np.fill_diagonal(c, 0.0)
    return float(c.max(initial=0.0))


def assignment(gain):
    """Columns that maximise the summed gain, one per row (rows <= columns after padding); shortest augmenting paths."""
    gain = np.asarray(gain, dtype=float)
    rows, cols = gain.shape
    size = max(rows, cols)
    cost = np.zeros((size, size))
    cost[:rows, :cols] = gain.max(initial=0.0) - gain
    u, v, match = np.zeros(size + 1), np.zeros(size + 1), np.zeros(size + 1, dtype=int)
    for i in range(1, size + 1):
        match[0], j0 = i, 0
        least, back, used = np.full(size + 1, np.inf), np.zeros(size + 1, dtype=int), np.zeros(size + 1, dtype=bool)
        while True:
            used[j0] = True
            i0 = match[j0]
            free = ~used[1:]
            slack = cost[i0 - 1] - u[i0] - v[1:]
            better = free & (slack < least[1:])
            least[1:][better], back[1:][better] = slack[better], j0
            j1 = 1 + int(np.where(free, least[1:], np.inf).argmin())
            step = least[j1]
            u[match[used]] += step
            v[used] -= step
            least[1:][free] -= step
            j0 = j1
            if match[j0] == 0:
                break
        while j0:
            match[j0], j0 = match[back[j0]], back[j0]
    out = np.full(rows, -1)
    for j in range(1, size + 1):
        if match[j] - 1 < rows and j - 1 < cols:
            out[match[j] - 1] = j - 1
    return out
