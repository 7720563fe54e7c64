"""DuckDB SQL for the engine's methods, generated from their definition and sharing no code with the engine.

``unrolled`` writes one block of common table expressions per flush.  It evaluates every curve at every point by
joins (no sweep, no numpy), finds brackets by conditional extremes, and interpolates.
"""

from __future__ import annotations

from collections.abc import Sequence
from math import exp, log


def levels_sql(levels: Sequence[float]) -> str:
    return "SELECT * FROM (VALUES " + ", ".join(f"({k}, CAST({float(p)!r} AS DOUBLE))" for k, p in enumerate(levels)) + ") AS lv(m, p)"


def _clip(p: str, n: str) -> str:
    return f"greatest(least({p}, 1 - 0.5 / {n}), 0.5 / {n})"


def _g(p: str, n: str, interp: str) -> str:
    return f"ln({_clip(p, n)} / (1 - {_clip(p, n)}))" if interp == "logit" else p


def _value(interp: str, plateau: str, bracket: str) -> str:
    """Value of one level from bracket columns (up_x, up_lo, up_hi, dn_*), total w, level p, extremes x0, x1."""
    a, b = ("dn_lo", "up_hi") if bracket == "outer" else ("dn_hi", "up_lo")
    ga, gb, gp = (_g(f"({v} / w)", "w", interp) for v in (a, b, "(p * w)"))
    gp = _g("p", "w", interp)
    rho = f"(CASE WHEN {gb} <> {ga} THEN least(greatest(({gb} - {gp}) / ({gb} - {ga}), 0), 1) ELSE 0.5 END)"
    flat = {"low": "up_x", "high": "dn_x", "mid": "(up_x + dn_x) / 2"}[plateau]
    return f"CASE WHEN p <= 0 THEN x0 WHEN p >= 1 THEN x1 WHEN dn_x > up_x THEN {flat} WHEN dn_x = up_x THEN up_x ELSE {rho} * dn_x + (1 - {rho}) * up_x END"


def unrolled(levels: Sequence[float], flushes: int, batch: int, raw: str | None = None, dig: str | None = None, interp: str = "linear", plateau: str = "mid", limits: str = "as_stated", bracket: str = "outer", decay: float = 1.0) -> str:
    """CTE text that ends in ``kn_<flushes>(k, m, p, v, w)``: the knots of every key after all flushes.

    raw: SQL of ``(k, rn, x)``; dig: SQL of ``(k, rn, cid, n, m, p, v)`` (stored values of digests, p untrimmed); rn
    counts records of a key from 1, over both kinds.
    """
    none_raw = "SELECT NULL AS k, 0 AS rn, CAST(0 AS DOUBLE) AS x WHERE false"
    none_dig = "SELECT NULL AS k, 0 AS rn, 0 AS cid, CAST(1 AS DOUBLE) AS n, 0 AS m, CAST(0 AS DOUBLE) AS p, CAST(0 AS DOUBLE) AS v WHERE false"
    if raw is None:
        none_raw = f"SELECT k, 0 AS rn, CAST(0 AS DOUBLE) AS x FROM ({dig}) AS z WHERE false"
    if dig is None:
        none_dig = f"SELECT k, 0 AS rn, 0 AS cid, CAST(1 AS DOUBLE) AS n, 0 AS m, CAST(0 AS DOUBLE) AS p, CAST(0 AS DOUBLE) AS v FROM ({raw}) AS z WHERE false"
    out = [f"lv AS MATERIALIZED ({levels_sql(levels)})", f"raw_all AS MATERIALIZED ({raw or none_raw})", f"dig_all AS MATERIALIZED ({dig or none_dig})"]
    out.append("kn_0 AS MATERIALIZED (SELECT k, 0 AS m, CAST(0 AS DOUBLE) AS p, x AS v, CAST(0 AS DOUBLE) AS w FROM raw_all WHERE false)")
    for f in range(1, flushes + 1):
        lo, hi, prev = (f - 1) * batch + 1, f * batch, f"kn_{f - 1}"
        out += [
            f"r_{f} AS MATERIALIZED (SELECT k, x FROM raw_all WHERE rn BETWEEN {lo} AND {hi})",
            f"d_{f} AS MATERIALIZED (SELECT k, CAST(cid AS BIGINT) AS cid, n AS w, m, {_clip('p', 'n')} AS q, v FROM dig_all WHERE rn BETWEEN {lo} AND {hi})",
            f"act_{f} AS MATERIALIZED (SELECT DISTINCT k FROM (SELECT k FROM r_{f} UNION ALL SELECT k FROM d_{f}) AS u)",
            # all knot curves of this flush: the digests, and the knots so far with their (decayed) weight
            f"c_{f} AS MATERIALIZED (SELECT k, cid, w, m, q, v FROM d_{f} UNION ALL SELECT k, -1, w * {decay!r}, m, {_clip('p', f'(w * {decay!r})')}, v FROM {prev} WHERE k IN (SELECT k FROM act_{f}))",
            f"pt_{f} AS MATERIALIZED (SELECT DISTINCT k, x FROM (SELECT k, x FROM r_{f} UNION ALL SELECT k, v FROM c_{f}) AS u)",
            f"st_{f} AS MATERIALIZED (SELECT p.k, p.x, count(r.x) FILTER (WHERE r.x < p.x) AS lo, count(r.x) FILTER (WHERE r.x <= p.x) AS hi FROM pt_{f} AS p LEFT JOIN r_{f} AS r ON r.k = p.k GROUP BY p.k, p.x)",
            f"cs_{f} AS MATERIALIZED (SELECT k, cid, max(m) AS last, any_value(w) AS w FROM c_{f} GROUP BY k, cid)",
            f"at_{f} AS MATERIALIZED (SELECT p.k, p.x, s.cid, s.w, s.last, max(c.m) FILTER (WHERE c.v <= p.x) AS m, min(c.m) FILTER (WHERE c.v = p.x) AS tie FROM pt_{f} AS p JOIN cs_{f} AS s ON s.k = p.k JOIN c_{f} AS c ON c.k = p.k AND c.cid = s.cid GROUP BY p.k, p.x, s.cid, s.w, s.last)",
        ]
        ya, yb = ("ln(a.q / (1 - a.q))", "ln(b.q / (1 - b.q))") if interp == "logit" else ("a.q", "b.q")
        mid = f"({ya} + ({yb} - {ya}) * (t.x - a.v) / (b.v - a.v))"
        mid = f"(1 / (1 + exp(-{mid})))" if interp == "logit" else mid
        right = f"CASE WHEN t.m IS NULL THEN 0 WHEN t.m = t.last THEN 1 ELSE {mid} END"
        left = "h" if limits == "as_stated" else "CASE WHEN tie IS NULL THEN h WHEN tie = 0 THEN 0 ELSE tq END"
        out += [
            f"kc_{f} AS MATERIALIZED (SELECT t.k, t.x, t.w, t.tie, e.q AS tq, {right} AS h FROM at_{f} AS t LEFT JOIN c_{f} AS a ON a.k = t.k AND a.cid = t.cid AND a.m = t.m LEFT JOIN c_{f} AS b ON b.k = t.k AND b.cid = t.cid AND b.m = t.m + 1 LEFT JOIN c_{f} AS e ON e.k = t.k AND e.cid = t.cid AND e.m = t.tie)",
            f"ks_{f} AS MATERIALIZED (SELECT k, x, sum(w * h) AS hi, sum(w * ({left})) AS lo FROM kc_{f} GROUP BY k, x)",
            f"tw_{f} AS MATERIALIZED (SELECT a.k, coalesce((SELECT sum(w) FROM cs_{f} AS s WHERE s.k = a.k), 0) + (SELECT count(*) FROM r_{f} AS r WHERE r.k = a.k) AS w FROM act_{f} AS a)",
            f"li_{f} AS MATERIALIZED (SELECT s.k, s.x, s.lo + coalesce(c.lo, 0) AS lo, s.hi + coalesce(c.hi, 0) AS hi, CAST(t.w AS DOUBLE) AS w FROM st_{f} AS s JOIN tw_{f} AS t ON t.k = s.k LEFT JOIN ks_{f} AS c ON c.k = s.k AND c.x = s.x)",
        ]
        out += _inversion(f, f"li_{f}", interp, plateau, bracket)
        out.append(f"kn_{f} AS MATERIALIZED (SELECT k, m, p, v, w FROM iv_{f} UNION ALL SELECT k, m, p, v, w FROM {prev} WHERE k NOT IN (SELECT k FROM act_{f}))")
    return ",\n".join(out)


def _inversion(f: int | str, limits: str, interp: str, plateau: str, bracket: str) -> list[str]:
    return [
        f"br_{f} AS MATERIALIZED (SELECT l.k, lv.m, lv.p, any_value(l.w) AS w, min(l.x) AS x0, max(l.x) AS x1, min(l.x) FILTER (WHERE l.hi >= lv.p * l.w - 1e-12 * l.w) AS up_x, max(l.x) FILTER (WHERE l.lo <= lv.p * l.w + 1e-12 * l.w) AS dn_x FROM {limits} AS l CROSS JOIN lv GROUP BY l.k, lv.m, lv.p)",
        f"bx_{f} AS MATERIALIZED (SELECT b.k, b.m, b.p, b.w, b.x0, b.x1, u.x AS up_x, u.lo AS up_lo, u.hi AS up_hi, d.x AS dn_x, d.lo AS dn_lo, d.hi AS dn_hi FROM br_{f} AS b JOIN {limits} AS u ON u.k = b.k AND u.x = coalesce(b.up_x, b.x1) JOIN {limits} AS d ON d.k = b.k AND d.x = coalesce(b.dn_x, b.up_x))",
        f"iv_{f} AS MATERIALIZED (SELECT k, m, p, {_value(interp, plateau, bracket)} AS v, w FROM bx_{f})",
    ]


def final(cte: str, flushes: int, select: str = "k, p AS level, round(v, 6) AS value", where: str = "") -> str:
    return f"WITH {cte}\nSELECT {select} FROM kn_{flushes} {where}"


def one_blend(levels: Sequence[float], dig: str, raw: str | None = None, interp: str = "linear", plateau: str = "mid", limits: str = "as_stated", bracket: str = "outer") -> str:
    """All digests of a key in one flush, evaluated curve by curve."""
    return unrolled(levels, 1, 10**12, raw, dig, interp, plateau, limits, bracket)


def logit_list(m: int, eps: float) -> list[float]:
    edge = log((1 - eps) / eps)
    step = 2 * edge / (m - 3)
    return [0.0, *[1 / (1 + exp(-(-edge + k * step))) for k in range(m - 2)], 1.0]


def uniform_list(m: int) -> list[float]:
    return [k / (m - 1) for k in range(m)]


def exact_digests(source: str, key: str, value: str, levels: Sequence[float], plateau: str = "mid") -> str:
    """Digests of whole groups as one batch: ``(key, n, m, p, v)`` by ranks, for groups of any size."""
    pick = {"low": "lo", "high": "hi", "mid": "(lo + hi) / 2"}[plateau]
    return f"""SELECT g.k, g.n, lv.m, lv.p, (SELECT {pick} FROM (SELECT CAST(min(x) FILTER (WHERE s.up >= lv.p * g.n - 1e-12 * g.n) AS DOUBLE) AS lo, CAST(max(x) FILTER (WHERE s.dn <= lv.p * g.n + 1e-12 * g.n) AS DOUBLE) AS hi FROM cum AS s WHERE s.k = g.k) AS z) AS v FROM (SELECT k, any_value(n) AS n FROM cum GROUP BY k) AS g CROSS JOIN ({levels_sql(levels)}) AS lv"""


def read_out(levels: Sequence[float], knots: str) -> str:
    """CTEs that end in ``kn_1``: knots ``(k, n, m, p, v)`` of every key read at other levels."""
    return unrolled(levels, 1, 10**9, None, f"SELECT k, 1 AS rn, 1 AS cid, n, m, p, v FROM ({knots}) AS knots")


def tracker(raw: str, p: float, weight: float | None = None, first: int = 20) -> str:
    """Stochastic approximation of one quantile, one step a value: ``k, n, level, value`` of ``(k, rn, x)``."""
    a = "(1 / CAST(e.n AS DOUBLE))" if weight is None else repr(weight)
    h = f"(s.r / sqrt(e.n / {float(first)}))" if weight is None else "(s.r / 2)"
    f = f"((1 - {a}) * s.f + {a} * CAST(abs(e.x - s.q) <= {h} AS DOUBLE) / (2 * {h}))"
    q = f"(s.q + {a} / greatest({f}, CAST(0.1 AS DOUBLE) / s.r / sqrt(e.n)) * ({p!r}::DOUBLE - CAST(e.x <= s.q AS DOUBLE)))"
    return f"""WITH raw AS MATERIALIZED ({raw}),
e0 AS (SELECT k, quantile_cont(x, {p}) AS q, greatest(quantile_cont(x, 0.75) - quantile_cont(x, 0.25), 1e-9) AS r FROM raw WHERE rn <= {first} GROUP BY k),
e1 AS (SELECT e0.k, any_value(q) AS q, any_value(r) AS r, greatest(avg(CAST(abs(x - q) <= r AS DOUBLE)) / (2 * any_value(r)), 1e-12) AS f FROM e0 JOIN raw USING (k) WHERE rn <= {first} GROUP BY e0.k),
steps AS (SELECT k, list(struct_pack(n := rn, x := CAST(x AS DOUBLE), q := q, r := r, f := f) ORDER BY rn) AS l, count(*) AS n FROM raw JOIN e1 USING (k) WHERE rn >= least({first}, (SELECT count(*) FROM raw AS c WHERE c.k = e1.k)) GROUP BY k)
SELECT k, max(rn) AS n, CAST({p} AS DOUBLE) AS level, any_value(v) AS value FROM raw JOIN (SELECT k, list_reduce(l, lambda s, e: struct_pack(n := e.n, x := e.x, q := {q}, r := s.r, f := {f})).q AS v FROM steps) AS z USING (k) GROUP BY k"""


def brackets(raw: str, levels: Sequence[float], size: int = 50) -> str:
    """Bracketing buffers of ``size`` values, one value a step: ``k, level, value`` of ``(k, rn, x)``."""
    low, high = f"(e.n > {size} AND e.x < s.b[1])", f"(e.n > {size} AND e.x > s.b[len(s.b)])"
    b, under = f"(CASE WHEN {low} OR {high} THEN s.b ELSE list_sort(list_append(s.b, e.x)) END)", f"(s.u + CAST({low} AS BIGINT))"
    drop = f"(s.p * e.n - {under} > len({b}) / 2.0::DOUBLE)"
    b2 = f"(CASE WHEN len({b}) <= {size} THEN {b} WHEN {drop} THEN {b}[2:] ELSE {b}[:{size}] END)"
    u2 = f"({under} + CAST(len({b}) > {size} AND {drop} AS BIGINT))"
    return f"""WITH raw AS ({raw}),
steps AS (SELECT k, lv.p, list(struct_pack(n := rn, x := CAST(x AS DOUBLE), p := lv.p, b := [CAST(x AS DOUBLE)], u := CAST(0 AS BIGINT)) ORDER BY rn) AS l FROM raw CROSS JOIN ({levels_sql(levels)}) AS lv GROUP BY k, lv.p),
ends AS (SELECT k, p, list_reduce(l, lambda s, e: struct_pack(n := e.n, x := e.x, p := s.p, b := {b2}, u := {u2})) AS s FROM steps)
SELECT k, p AS level, s.b[CAST(greatest(0, least(len(s.b) - 1, ceil(p * s.n) - s.u - 1)) AS BIGINT) + 1] AS value FROM ends"""
