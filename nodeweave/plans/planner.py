"""How a moment pass should run, from sizes alone."""

from __future__ import annotations

#: Largest number of variables whose p x p moment is kept by every task and the driver.
LOCAL_P_MAX = 5000


def choose_strategy(n: int | None, p: int, k: int, m: int, moment_mode: str = "sign_split") -> str:
    """``gram`` (sums of r x x'), or ``product`` (sums of r x (x'W)) where p x p is too large or the run is huge.

    ``absolute`` and ``sign_split`` moments need the whole matrix; beyond LOCAL_P_MAX variables the product strategy takes
    signed moments in their place (:func:`moment_mode_for`). ``n``: number of samples, if known.
    """
    if p > LOCAL_P_MAX:
        return "product"
    if moment_mode in ("absolute", "sign_split"):
        return "gram"
    cheap = n is not None and n * p * p * m < 1e12
    return "gram" if cheap or p <= 512 else "product"


def moment_mode_for(strategy: str, moment_mode: str) -> str:
    """The moments that a strategy can use."""
    return "signed" if strategy == "product" else moment_mode


def pass_cost(n: int, p: int, k: int, m: int, tasks: int, strategy: str) -> dict[str, float]:
    """Floating-point operations, bytes a task holds and bytes shuffled by one pass."""
    if strategy == "gram":
        return {"flops": 2.0 * n * p * p * m + 2.0 * n * m * (p * k + k * k), "task_bytes": 4.0 * max(m - 1, 1) * p * (p + 1), "shuffle_bytes": 4.0 * tasks * max(m - 1, 1) * p * (p + 1)}
    if strategy == "product":
        return {"flops": 4.0 * n * p * k * m, "task_bytes": 8.0 * m * p * k, "shuffle_bytes": 8.0 * tasks * m * p * k}
    if strategy == "sql":
        return {"flops": float(n) * p * p, "task_bytes": 0.0, "shuffle_bytes": 16.0 * n * p + 24.0 * tasks * p * p}
    raise ValueError(f"unknown strategy {strategy!r}")


def explain_strategy(n: int, p: int, k: int, m: int, moment_mode: str = "sign_split", tasks: int = 1000) -> str:
    """The choice and what each alternative would cost."""
    chosen = choose_strategy(n, p, k, m, moment_mode)
    lines = [f"n={n} p={p} k={k} m={m} {moment_mode}: {chosen}"]
    for s in ("gram", "product", "sql"):
        c = pass_cost(n, p, k, m, tasks, s)
        lines.append(f"  {s}: {c['flops']:.3g} flop, {c['task_bytes'] / 1e6:.3g} MB a task, {c['shuffle_bytes'] / 1e6:.3g} MB shuffled")
    return "\n".join(lines)
