"""SQL that unrolls EM rounds as chains of common table expressions: an independent form for checks."""

from __future__ import annotations

LOG_2PI = "1.8378770664093453e0"


def names_of(d: int, cov: str) -> list[str]:
    pairs = [(i, j) for i in range(d) for j in range(i, d) if cov == "full" or i == j]
    return [f"mu{i}" for i in range(d)] + [f"s{i}{j}" for i, j in pairs]


def gaussian_log(d: int, cov: str) -> str:
    u = [f"(x{i} - mu{i})" for i in range(d)]
    if cov == "diag" or d == 1:
        return "ln(w) - 0.5e0 * (" + " + ".join(f"{LOG_2PI} + ln(s{i}{i}) + {u[i]} * {u[i]} / s{i}{i}" for i in range(d)) + ")"
    if d == 2:
        det = "(s00 * s11 - s01 * s01)"
        quad = f"(s11 * {u[0]} * {u[0]} - 2 * s01 * {u[0]} * {u[1]} + s00 * {u[1]} * {u[1]}) / {det}"
    else:
        a = {(0, 0): "(s11 * s22 - s12 * s12)", (0, 1): "(s02 * s12 - s01 * s22)", (0, 2): "(s01 * s12 - s02 * s11)", (1, 1): "(s00 * s22 - s02 * s02)", (1, 2): "(s01 * s02 - s00 * s12)", (2, 2): "(s00 * s11 - s01 * s01)"}
        det = f"(s00 * {a[0, 0]} + s01 * {a[0, 1]} + s02 * {a[0, 2]})"
        quad = "(" + " + ".join(f"{1 if i == j else 2} * {c} * {u[i]} * {u[j]}" for (i, j), c in a.items()) + f") / {det}"
    return f"ln(w) - {d} * 0.5e0 * {LOG_2PI} - 0.5e0 * ln({det}) - 0.5e0 * ({quad})"


def _values(rows: list[tuple]) -> str:
    return ", ".join("(" + ", ".join(str(v) if isinstance(v, int) else f"{v!r}e0" if "e" not in repr(v) else repr(v) for v in r) + ")" for r in rows)


def gaussian(data: str, start: list[tuple], d: int, cov: str, rounds: int) -> str:
    """WITH chain: data ``x``, models ``m0..m{rounds}`` (comp, w, mu.., s..) and E-steps ``e{t}`` (with p and lse)."""
    names = names_of(d, cov)
    out = [f"x AS ({data})", f"m0(comp, w, {', '.join(names)}) AS (SELECT * FROM (VALUES {_values(start)}) v)"]
    for t in range(rounds + 1):
        out += estep(f"m{t}", t, gaussian_log(d, cov))
        if t == rounds:
            break
        means = ", ".join(f"sum(p * x{i}) / sum(p) AS n{i}" for i in range(d))
        out.append(f"n{t} AS (SELECT comp AS c, sum(p) AS s, {means} FROM e{t} GROUP BY comp)")
        pairs = [n[1:] for n in names if n[0] == "s"]
        covs = ", ".join(f"sum(p * (x{a} - n{a}) * (x{b} - n{b})) / max(s) AS s{a}{b}" for a, b in pairs)
        mus = ", ".join(f"max(n{i}) AS mu{i}" for i in range(d))
        out.append(f"m{t + 1} AS (SELECT comp, max(s) / (SELECT count(*) FROM x) AS w, {mus}, {covs} FROM e{t} JOIN n{t} ON comp = c GROUP BY comp)")
    return "WITH " + ",\n".join(o.replace(" AS (", " AS MATERIALIZED (", 1) for o in out)


def estep(model: str, t: int, log: str) -> list[str]:
    return [
        f"l{t} AS (SELECT *, {log} AS l FROM x CROSS JOIN {model})",
        f"q{t} AS (SELECT *, max(l) OVER (PARTITION BY tid) AS top FROM l{t})",
        f"e{t} AS (SELECT *, top + ln(sum(exp(l - top)) OVER (PARTITION BY tid)) AS lse, exp(l - top) / sum(exp(l - top)) OVER (PARTITION BY tid) AS p FROM q{t})",
    ]


def regression(data: str, start: list[tuple], rounds: int, gated: bool) -> str:
    """One feature and an intercept. Models ``m{t}``: (comp, w | g0, g1, b0, b1, v), slopes before intercepts."""
    head = "comp, g0, g1, b0, b1, v" if gated else "comp, w, b0, b1, v"
    out = [f"x AS ({data})", f"m0({head}) AS (SELECT * FROM (VALUES {_values(start)}) z)"]
    fit = "- 0.5e0 * (" + LOG_2PI + " + ln(v)) - 0.5e0 * (y - b0 * x0 - b1) * (y - b0 * x0 - b1) / v"
    for t in range(rounds + 1):
        if gated:
            out.append(f"a{t} AS (SELECT *, g0 * x0 + g1 AS a FROM x CROSS JOIN m{t})")
            out.append(f"b{t} AS (SELECT *, a - max(a) OVER (PARTITION BY tid) AS aa FROM a{t})")
            out.append(f"l{t} AS (SELECT *, aa - ln(sum(exp(aa)) OVER (PARTITION BY tid)) {fit} AS l FROM b{t})")
        else:
            out.append(f"l{t} AS (SELECT *, ln(w) {fit} AS l FROM x CROSS JOIN m{t})")
        out += [o for o in estep(f"m{t}", t, "0") if not o.startswith(f"l{t} ")]
        if t == rounds:
            break
        out.append(f"h{t} AS (SELECT comp AS c, sum(p) AS s, sum(p * x0) AS sx, sum(p * x0 * x0) AS sxx, sum(p * y) AS sy, sum(p * x0 * y) AS sxy FROM e{t} GROUP BY comp)")
        out.append(f"k{t} AS (SELECT c, s, (s * sxy - sx * sy) / (s * sxx - sx * sx) AS n0, (sxx * sy - sx * sxy) / (s * sxx - sx * sx) AS n1 FROM h{t})")
        var = "sum(p * (y - n0 * x0 - n1) * (y - n0 * x0 - n1)) / max(s) AS v"
        if not gated:
            out.append(f"m{t + 1} AS (SELECT comp, max(s) / (SELECT count(*) FROM x) AS w, max(n0) AS b0, max(n1) AS b1, {var} FROM e{t} JOIN k{t} ON comp = c GROUP BY comp)")
            continue
        out.append(f"t{t} AS (SELECT tid, comp, x0, ln(greatest(p, 1e-6)) - avg(ln(greatest(p, 1e-6))) OVER (PARTITION BY tid) AS target FROM e{t})")
        out.append(f"u{t} AS (SELECT comp, count(*) AS n, sum(x0) AS sx, sum(x0 * x0) AS sxx, sum(target) AS st, sum(x0 * target) AS sxt FROM t{t} GROUP BY comp)")
        out.append(f"w{t} AS (SELECT comp, (n * sxt - sx * st) / (n * sxx - sx * sx) AS r0, (sxx * st - sx * sxt) / (n * sxx - sx * sx) AS r1 FROM u{t})")
        out.append(f"z{t} AS (SELECT comp AS c2, r0 - avg(r0) OVER () AS g0, r1 - avg(r1) OVER () AS g1 FROM w{t})")
        out.append(f"m{t + 1} AS (SELECT comp, max(z{t}.g0) AS g0, max(z{t}.g1) AS g1, max(n0) AS b0, max(n1) AS b1, {var} FROM e{t} JOIN k{t} ON comp = c JOIN z{t} ON comp = c2 GROUP BY comp)")
    return "WITH " + ",\n".join(o.replace(" AS (", " AS MATERIALIZED (", 1) for o in out)
