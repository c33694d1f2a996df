"""Iterative estimators as SQL: a few steps unrolled into common table expressions.

The text is what another engine can run beside the estimators to check them step by step. Matrices are
tables (g, i, j, v), where g is a state or group; vectors (g, i, v). Every expression is materialised,
as each is read several times.
"""

from __future__ import annotations

import numpy as np


def number(v: float) -> str:
    return f"CAST({float(v)!r} AS DOUBLE)"


class Steps:
    """Common table expressions in order; each method adds some and returns the name of the last."""

    def __init__(self, head: str):
        self.parts = [head]
        self.count = 0

    def add(self, sql: str, name: str | None = None) -> str:
        self.count += 1
        name = name or f"u{self.count}"
        self.parts.append(f"{name} AS MATERIALIZED ({sql})")
        return name

    def text(self, last: str) -> str:
        return f"WITH {', '.join(self.parts)} {last}"

    # ---- matrices ---------------------------------------------------------------------------------

    def constant(self, matrices) -> str:
        rows = ", ".join(f"({g}, {i}, {j}, {number(v)})" for g, m in enumerate(matrices) for (i, j), v in np.ndenumerate(np.asarray(m)))
        return self.add(f"SELECT * FROM (VALUES {rows}) t(g, i, j, v)")

    def product(self, a: str, b: str, first: bool = False, second: bool = False) -> str:
        """a b, with a or b transposed where asked for."""
        ai, aj = ("j", "i") if first else ("i", "j")
        bi, bj = ("j", "i") if second else ("i", "j")
        return self.add(f"SELECT x.g AS g, x.{ai} AS i, y.{bj} AS j, sum(x.v * y.v) AS v FROM {a} x JOIN {b} y ON x.g = y.g AND x.{aj} = y.{bi} GROUP BY 1, 2, 3")

    def cells(self, a: str, b: str, value: str) -> str:
        """``value`` of x.v and y.v, cell by cell."""
        return self.add(f"SELECT x.g, x.i, x.j, {value} AS v FROM {a} x JOIN {b} y ON x.g = y.g AND x.i = y.i AND x.j = y.j")

    def map(self, a: str, value: str) -> str:
        return self.add(f"SELECT g, i, j, {value} AS v FROM {a}")

    def unit_columns(self, a: str) -> str:
        return self.add(f"SELECT g, i, j, v / sqrt(sum(v * v) OVER (PARTITION BY g, j)) AS v FROM {a}")

    def inverse(self, a: str, n: int) -> tuple[str, str]:
        """The inverse and (g, v) of the log determinant, by elimination in place."""
        pivots = []
        for k in range(n):
            pivots.append(f"SELECT g, ln(v) AS v FROM {a} WHERE i = {k} AND j = {k}")
            a = self.add(f"""SELECT x.g, x.i, x.j, CASE WHEN x.i = {k} AND x.j = {k} THEN 1 / p.v WHEN x.i = {k} THEN x.v / p.v WHEN x.j = {k} THEN -x.v / p.v ELSE x.v - c.v * r.v / p.v END AS v
FROM {a} x JOIN {a} p ON p.g = x.g AND p.i = {k} AND p.j = {k} JOIN {a} r ON r.g = x.g AND r.i = {k} AND r.j = x.j JOIN {a} c ON c.g = x.g AND c.i = x.i AND c.j = {k}""")
        return a, self.add(f"SELECT g, sum(v) AS v FROM ({' UNION ALL '.join(pivots)}) GROUP BY g")

    def pair(self, a: str) -> str:
        """(g, a, b, c) of symmetric 2 x 2 matrices [[a, b], [b, c]]."""
        return self.add(f"SELECT g, max(CASE WHEN i = 0 AND j = 0 THEN v END) AS a, max(CASE WHEN i = 0 AND j = 1 THEN v END) AS b, max(CASE WHEN i = 1 AND j = 1 THEN v END) AS c FROM {a} GROUP BY g")

    def unpair(self, p: str) -> str:
        return self.add(f"SELECT g, 0 AS i, 0 AS j, a AS v FROM {p} UNION ALL SELECT g, 0, 1, b FROM {p} UNION ALL SELECT g, 1, 0, b FROM {p} UNION ALL SELECT g, 1, 1, c FROM {p}")

    def inverse_pair(self, p: str) -> str:
        return self.add(f"SELECT g, c / (a * c - b * b) AS a, -b / (a * c - b * b) AS b, a / (a * c - b * b) AS c FROM {p}")

    # ---- estimators -------------------------------------------------------------------------------

    def node_precision(self, s: str, l1: float) -> str:
        """Sparse precision of 2 x 2 moments in closed form, as pairs."""
        p = self.pair(s)
        held = self.add(f"SELECT g, a + {number(l1)} AS a, sign(b) * greatest(abs(b) - {number(l1)}, 0) AS b, c + {number(l1)} AS c FROM {p}")
        return self.inverse_pair(held)

    def node_moment(self, w: str, a: str) -> str:
        return self.product(self.product(w, a, first=True), w)

    def remainder(self, w: str, a: str, s: str, p: int, k: int = 2) -> str:
        """(g, v): mean variance outside the span of W."""
        inverse = self.unpair(self.inverse_pair(self.pair(self.product(w, w, first=True))))
        inside = self.product(inverse, s)
        return self.add(f"SELECT t.g, (t.v - n.v) / {p - k} AS v FROM (SELECT g, sum(v) AS v FROM {a} WHERE i = j GROUP BY g) t JOIN (SELECT g, sum(v) AS v FROM {inside} WHERE i = j GROUP BY g) n ON n.g = t.g")

    def membership(self, w: str, a: str, omega: str, mode: str = "sign_split", floor: float = 1e-10) -> str:
        """One multiplicative step with unit columns; ``omega`` is a matrix."""
        up, down = self.map(omega, "greatest(v, 0)"), self.map(omega, "greatest(-v, 0)")
        multiplier = self.map(self.product(self.product(self.product(w, a, first=True), w), omega), "-v")
        plus, minus = self.map(multiplier, "greatest(v, 0)"), self.map(multiplier, "greatest(-v, 0)")
        if mode == "sign_split":
            pw, nw = self.product(self.map(a, "greatest(v, 0)"), w), self.product(self.map(a, "greatest(-v, 0)"), w)
            over = self.cells(self.product(pw, down), self.product(nw, up), "x.v + y.v")
            under = self.cells(self.product(pw, up), self.product(nw, down), "x.v + y.v")
        else:
            aw = self.product(a, w)
            over, under = self.product(aw, down), self.product(aw, up)
        over, under = self.cells(over, self.product(w, minus), "x.v + y.v"), self.cells(under, self.product(w, plus), "x.v + y.v")
        ratio = self.cells(over, under, f"greatest(x.v, {number(floor)}) / greatest(y.v, {number(floor)})")
        return self.unit_columns(self.cells(w, ratio, "x.v * y.v"))

    def coupled(self, a: str, w: str, l1: float, rounds: int) -> tuple[str, str]:
        """Rounds of precision and membership on a moment; the last W and its precision (pairs)."""
        for _ in range(rounds):
            w = self.membership(w, a, self.unpair(self.node_precision(self.node_moment(w, a), l1)))
        return w, self.node_precision(self.node_moment(w, a), l1)

    def tri_factor(self, a: str, w: str, rounds: int) -> tuple[str, str]:
        """Steps of the orthogonal tri-factorisation of |a|; W and the middle factor."""
        a = self.map(a, "abs(v)")
        s = self.node_moment(w, a)
        for _ in range(rounds):
            aws = self.product(self.product(a, w), s)
            under = self.product(w, self.product(w, aws, first=True))
            w = self.unit_columns(self.cells(w, self.cells(aws, under, "sqrt(x.v / greatest(y.v, 1e-12))"), "x.v * y.v"))
            inverse = self.unpair(self.inverse_pair(self.pair(self.product(w, w, first=True))))
            s = self.map(self.product(self.product(inverse, self.node_moment(w, a)), inverse), "greatest(v, 0)")
        return w, s

    def factors(self, a: str, f: str, g: str, rounds: int) -> tuple[str, str]:
        """Multiplicative steps of a non-negative factorisation of max(a, 0) into F G'."""
        a = self.map(a, "greatest(v, 0)")
        ratio = "x.v / greatest(y.v, 1e-12)"
        for _ in range(rounds):
            f = self.cells(f, self.cells(self.product(a, g), self.product(f, self.product(g, g, first=True)), ratio), "x.v * y.v")
            g = self.cells(g, self.cells(self.product(a, f, first=True), self.product(g, self.product(f, f, first=True)), ratio), "x.v * y.v")
        return f, g

    def symmetric_factor(self, a: str, f: str, rounds: int) -> str:
        a = self.map(a, "greatest(v, 0)")
        for _ in range(rounds):
            ratio = self.cells(self.product(a, f), self.product(f, self.product(f, f, first=True)), "0.5 + 0.5 * x.v / greatest(y.v, 1e-12)")
            f = self.cells(f, ratio, "x.v * y.v")
        return f

    def lloyd(self, samples: str, centres, steps: int) -> tuple[str, str]:
        """k-means from given centres over (sample_id, var_id, value): (sample_id, g) after ``steps`` of new centres, and the centres of these groups."""
        c = self.constant([centres])
        for _ in range(steps + 1):
            near = self.add(f"SELECT sample_id, CAST(arg_min(c, d) AS INTEGER) AS g FROM (SELECT e.sample_id, x.i AS c, sum((e.value - x.v) * (e.value - x.v)) AS d FROM {samples} e JOIN {c} x ON x.j = e.var_id GROUP BY 1, 2) GROUP BY 1")
            c = self.add(f"SELECT 0 AS g, n.g AS i, e.var_id AS j, avg(e.value) AS v FROM {samples} e JOIN {near} n USING (sample_id) GROUP BY 2, 3")
        return near, c

    def grouped_moments(self, samples: str, groups: str) -> str:
        return self.add(f"SELECT n.g, a.var_id AS i, b.var_id AS j, sum(a.value * b.value) / count(*) AS v FROM {groups} n JOIN {samples} a USING (sample_id) JOIN {samples} b USING (sample_id) GROUP BY 1, 2, 3")

    def weighted_moments(self, samples: str, r: str) -> str:
        """Moments under responsibilities (sample_id, g, r)."""
        return self.add(f"SELECT n.g, a.var_id AS i, b.var_id AS j, sum(n.r * a.value * b.value) / sum(n.r) AS v FROM {r} n JOIN {samples} a USING (sample_id) JOIN {samples} b USING (sample_id) GROUP BY 1, 2, 3")

    def shares(self, r: str) -> str:
        return self.add(f"SELECT g, sum(r) / (SELECT count(DISTINCT sample_id) FROM {r}) AS v FROM {r} GROUP BY g")

    def posterior(self, z: str) -> str:
        """(sample_id, g, r, z) from log joint densities (sample_id, g, z)."""
        return self.add(f"SELECT sample_id, g, z, exp(z - m) / sum(exp(z - m)) OVER (PARTITION BY sample_id) AS r FROM (SELECT *, max(z) OVER (PARTITION BY sample_id) AS m FROM {z})")

    def full_density(self, samples: str, shares: str, omega: str, logdet: str, p: int) -> str:
        """Log joint densities of zero-mean states with p x p precisions."""
        square = self.add(f"SELECT a.sample_id, o.g, sum(a.value * o.v * b.value) AS q FROM {samples} a JOIN {samples} b USING (sample_id) JOIN {omega} o ON o.i = a.var_id AND o.j = b.var_id GROUP BY 1, 2")
        return self.add(f"SELECT q.sample_id, q.g, ln(s.v) + 5e-1 * d.v - 5e-1 * q.q - {p} * 5e-1 * ln(2 * pi()) AS z FROM {square} q JOIN {shares} s ON s.g = q.g JOIN {logdet} d ON d.g = q.g")

    def node_density(self, samples: str, shares: str, w: str, omega: str, tau: str | None, p: int) -> str:
        """Log joint densities of states with two nodes each; ``omega`` as pairs; with ``tau`` the residual density."""
        y = self.add(f"SELECT e.sample_id, w.g, sum(CASE WHEN w.j = 0 THEN e.value * w.v ELSE 0 END) AS y0, sum(CASE WHEN w.j = 1 THEN e.value * w.v ELSE 0 END) AS y1 FROM {samples} e JOIN {w} w ON w.i = e.var_id GROUP BY 1, 2")
        z = "ln(s.v) + 5e-1 * ln(o.a * o.c - o.b * o.b) - 5e-1 * (o.a * y0 * y0 + 2 * o.b * y0 * y1 + o.c * y1 * y1) - ln(2 * pi())"
        joined = f"FROM {y} y JOIN {shares} s ON s.g = y.g JOIN {omega} o ON o.g = y.g"
        if tau:
            gram = self.pair(self.product(w, w, first=True))
            size = self.add(f"SELECT sample_id, sum(value * value) AS v FROM {samples} GROUP BY 1")
            joined += f" JOIN {gram} m ON m.g = y.g JOIN {tau} t ON t.g = y.g JOIN {size} q ON q.sample_id = y.sample_id"
            det = "(m.a * m.c - m.b * m.b)"
            left = f"greatest(q.v - (m.c * y0 * y0 - 2 * m.b * y0 * y1 + m.a * y1 * y1) / {det}, 0)"
            z += f" + 5e-1 * ln({det}) - {p - 2} * 5e-1 * ln(2 * pi() * t.v) - {left} / (2 * t.v)"
        return self.add(f"SELECT y.sample_id, y.g, {z} AS z {joined}")

    def mixture(self, samples: str, p: int, start, l1: float, steps: int, density: str, update: str, product: bool = False) -> tuple[str, str, str, str | None]:
        """EM steps of the state mixture with two nodes a state: shares, W, omega (pairs), tau."""
        shares = self.add("SELECT * FROM (VALUES " + ", ".join(f"({j}, {number(v)})" for j, v in enumerate(start.shares)) + ") t(g, v)")
        w, omega = self.constant(start.w), self.pair(self.constant(start.omega))
        tau = self.add("SELECT * FROM (VALUES " + ", ".join(f"({j}, {number(v)})" for j, v in enumerate(start.tau)) + ") t(g, v)")
        for _ in range(steps):
            r = self.posterior(self.node_density(samples, shares, w, omega, tau if density == "residual" else None, p))
            shares, a = self.shares(r), self.weighted_moments(samples, r)
            s = self.node_moment(w, a)
            omega, tau = self.node_precision(s, l1), self.remainder(w, a, s, p)
            if update == "frozen":
                continue
            eff = self.unpair(omega)
            if density == "residual":
                eff = self.add(f"SELECT o.g, o.i, o.j, o.v - CASE WHEN o.i = o.j THEN 1 / t.v ELSE 0 END AS v FROM {eff} o JOIN {tau} t ON t.g = o.g")
            w = self.membership(w, a, eff, "signed" if product else "sign_split")
            if not product:  # the precision that belongs to the new membership
                s = self.node_moment(w, a)
                omega, tau = self.node_precision(s, l1), self.remainder(w, a, s, p)
        return shares, w, omega, tau
