"""SQL twins of iterative plans: a fixed number of rounds as common table expressions, for checks in another engine."""

from __future__ import annotations


class Ctes:
    """An ordered list of named queries; later ones may use earlier ones."""

    def __init__(self, *parts: tuple[str, str]):
        self.parts = list(parts)

    def add(self, name: str, body: str) -> Ctes:
        self.parts.append((name, body))
        return self

    def then(self, final: str) -> str:
        return "WITH RECURSIVE " + ",\n".join(f"{n} AS MATERIALIZED ({b})" if "RECURSE" not in n else f"{n.replace('RECURSE ', '')} AS ({b})" for n, b in self.parts) + "\n" + final

    def copy(self) -> Ctes:
        return Ctes(*self.parts)


def mix(alpha: float, out: str = "out_mass", inn: str = "in_mass") -> str:
    if alpha == 0:
        return inn
    if alpha == 1:
        return out
    return f"CASE WHEN {out} > 0 AND {inn} > 0 THEN pow({out}, {alpha}) * pow({inn}, {1 - alpha!r}) ELSE 0 END"


def forward(c: Ctes, edges: str, k: int, alpha: float, p: str = "") -> Ctes:
    """Adds ``{p}adj0..k`` (src, dst, w, a) and ``{p}st0..k`` (node, out_mass, in_mass, scale)."""
    c.add(f"{p}adj0", f"SELECT src, dst, w, w * w AS a FROM {edges}")
    for t in range(k + 1):
        c.add(f"{p}st{t}", f"SELECT node, out_mass, in_mass, ({mix(alpha)})::DOUBLE AS scale FROM (SELECT node, sum(o) AS out_mass, sum(i) AS in_mass FROM (SELECT src AS node, a AS o, 0.0::DOUBLE AS i FROM {p}adj{t} UNION ALL SELECT dst, 0.0::DOUBLE, a FROM {p}adj{t}) GROUP BY node)")
        if t < k:
            c.add(f"{p}adj{t + 1}", f"SELECT e.src, e.dst, e.w, CASE WHEN s.scale > 0 THEN e.a * d.scale / s.scale ELSE 0 END AS a FROM {p}adj{t} e JOIN {p}st{t} s ON e.src = s.node JOIN {p}st{t} d ON e.dst = d.node")
    return c


def gradient(c: Ctes, k: int, alpha: float, p: str = "") -> Ctes:
    """Adds ``{p}grad`` (src, dst, w, g) after ``forward``."""
    both = "out_mass > 0 AND in_mass > 0"
    for t in range(k + 1):
        c.add(f"{p}pt{t}", f"SELECT *, CASE WHEN {both} THEN {alpha} * pow(in_mass / out_mass, {1 - alpha!r}) ELSE 0 END AS fx, CASE WHEN {both} THEN {1 - alpha!r} * pow(out_mass / in_mass, {alpha}) ELSE 0 END AS fy FROM {p}st{t}")
    c.add(f"{p}p{k}", f"SELECT e.src, e.dst, s.fx + d.fy AS p FROM {p}adj{k} e JOIN {p}pt{k} s ON e.src = s.node JOIN {p}pt{k} d ON e.dst = d.node")
    for t in range(k - 1, -1, -1):
        c.add(f"{p}h{t}", f"SELECT e.src, e.dst, q.p, e.a, s.scale AS ss, d.scale AS sd, s.fx, d.fy FROM {p}adj{t} e JOIN {p}p{t + 1} q USING (src, dst) JOIN {p}pt{t} s ON e.src = s.node JOIN {p}pt{t} d ON e.dst = d.node")
        c.add(f"{p}u{t}", f"SELECT node, sum(v) AS u FROM (SELECT dst AS node, CASE WHEN ss > 0 THEN p * a / ss ELSE 0 END AS v FROM {p}h{t} UNION ALL SELECT src, CASE WHEN ss > 0 THEN -p * a * sd / (ss * ss) ELSE 0 END FROM {p}h{t}) GROUP BY node")
        c.add(f"{p}p{t}", f"SELECT h.src, h.dst, CASE WHEN ss > 0 THEN p * sd / ss ELSE 0 END + a.u * h.fx + b.u * h.fy AS p FROM {p}h{t} h JOIN {p}u{t} a ON h.src = a.node JOIN {p}u{t} b ON h.dst = b.node")
    return c.add(f"{p}grad", f"SELECT e.src, e.dst, e.w, 2 * q.p * e.w AS g FROM {p}adj0 e JOIN {p}p0 q USING (src, dst)")


def walks(c: Ctes, edges: str, length: int, p: str = "") -> Ctes:
    """Adds ``{p}closed`` (length, closed)."""
    c.add(f"{p}a", f"SELECT src, dst, w * w AS a FROM {edges}").add(f"{p}w1", f"SELECT src, dst, a AS v FROM {p}a")
    for m in range(2, length + 1):
        c.add(f"{p}w{m}", f"SELECT x.src, y.dst, sum(x.v * y.a) AS v FROM {p}w{m - 1} x JOIN {p}a y ON x.dst = y.src GROUP BY x.src, y.dst")
    rows = " UNION ALL ".join(f"SELECT {m} AS length, coalesce(sum(v), 0.0) AS closed FROM {p}w{m} WHERE src = dst" for m in range(1, length + 1))
    return c.add(f"{p}closed", rows)


def moment_loss(c: Ctes, moments: str, edges: str, lam: float, p: str = "") -> Ctes:
    """Adds ``{p}q`` (src, dst, w, q, t) and ``{p}fit`` (node, fit) from moments (a, b, c) with a <= b."""
    c.add(f"{p}m2", f"SELECT a, b, c FROM {moments} UNION ALL SELECT b, a, c FROM {moments} WHERE a <> b")
    c.add(f"{p}q", f"SELECT e.src, e.dst, e.w, coalesce(x.q, 0) AS q, coalesce(t.c, 0) AS t FROM {edges} e LEFT JOIN (SELECT e.src, e.dst, sum(m.c * o.w) AS q FROM {edges} e JOIN {edges} o ON e.dst = o.dst JOIN {p}m2 m ON m.a = e.src AND m.b = o.src GROUP BY e.src, e.dst) x ON e.src = x.src AND e.dst = x.dst LEFT JOIN {p}m2 t ON t.a = e.src AND t.b = e.dst")
    c.add(f"{p}fit", f"SELECT m.a AS node, m.c + coalesce(x.v, 0) AS fit FROM {moments} m LEFT JOIN (SELECT dst, sum(w * (q - 2 * t)) AS v FROM {p}q GROUP BY dst) x ON m.a = x.dst WHERE m.a = m.b")
    return c.add(f"{p}gl", f"SELECT src, dst, w, 2 * (q - t) + {lam} * sign(w) AS g FROM {p}q")
