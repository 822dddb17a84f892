"""DuckDB SQL that computes by brute force, over the joined rows, what the queries compute below the joins."""

from __future__ import annotations

from .sources.workloads import MATRIX_SQL


def matrix(name: str) -> str:
    return f"({MATRIX_SQL[name]})"


def marginal(name: str, feature: str, kind: str) -> str:
    num, cat = (f"{feature}::DOUBLE", "NULL::VARCHAR") if kind == "cont" else ("NULL::DOUBLE", feature)
    return f"SELECT '{feature}' AS subspace, {num} AS vnum, {cat} AS vcat, count(*)::BIGINT AS w FROM {matrix(name)} GROUP BY {feature}"


def marginals(name: str, features: dict[str, str]) -> str:
    return " UNION ALL ".join(marginal(name, f, k) for f, k in features.items())


def ranks(name: str, feature: str) -> str:
    return f"SELECT {feature} AS v, count(*) AS w, row_number() OVER (ORDER BY count(*) DESC, {feature}) - 1 AS rk FROM {matrix(name)} GROUP BY {feature}"


def heavy_light(name: str, feature: str, kappa: int) -> str:
    return f"""WITH r AS ({ranks(name, feature)})
SELECT '{feature}' AS subspace, rk::INT AS comp, 'heavy' AS kind, v AS vcat, w::BIGINT AS w FROM r WHERE rk < {kappa - 1}
UNION ALL SELECT '{feature}', {kappa - 1}, 'light', NULL, sum(w)::BIGINT FROM r WHERE rk >= {kappa - 1} HAVING count(*) > 0"""


def line_ctes(source: str, value: str, kappa: int, tag: str, p: int = 2, lam: float = 0.0) -> str:
    """CTEs of the dynamic program, a level each; {tag}_ends (q, e, hi) are the segments' ends. Needs at least kappa distinct values."""
    out = [
        f"{tag}_v AS (SELECT {value}::DOUBLE AS x, count(*)::DOUBLE AS w FROM {source} GROUP BY 1)",
        f"{tag}_m AS (SELECT sum(w*x)/sum(w) AS m FROM {tag}_v)",
        f"{tag}_p AS (SELECT row_number() OVER o AS i, x, w, sum(w) OVER o AS pw, sum(w*(x-m)) OVER o AS ps, sum(w*(x-m)*(x-m)) OVER o AS pq, sum(w*x) OVER o AS pr FROM {tag}_v, {tag}_m WINDOW o AS (ORDER BY x ROWS UNBOUNDED PRECEDING))",
        f"{tag}_z AS (SELECT i, x, pw, ps, pq, pr FROM {tag}_p UNION ALL SELECT 0, NULL, 0, 0, 0, 0)",
    ]
    if p == 2:
        base = "greatest(b.pq-a.pq-(b.ps-a.ps)*(b.ps-a.ps)/(b.pw-a.pw), 0)"
        if lam:
            mean = f"((b.ps-a.ps)/(b.pw-a.pw)+(SELECT m FROM {tag}_m))"
            cen = f"(sign({mean})*greatest(abs({mean})-{lam}/(2*(b.pw-a.pw)),0))"
            base = f"{base}+(b.pw-a.pw)*({mean}-{cen})*({mean}-{cen})+{lam}*abs({cen})"
        out.append(f"{tag}_c AS (SELECT a.i AS s, b.i AS e, {base} AS c FROM {tag}_z a JOIN {tag}_z b ON a.i < b.i)")
    else:
        out.append(f"{tag}_c AS (SELECT a.i AS s, b.i AS e, (SELECT min(d) FROM (SELECT (SELECT sum(y.w*abs(y.x-t.x)) FROM {tag}_p y WHERE y.i > a.i AND y.i <= b.i) AS d FROM {tag}_p t WHERE t.i > a.i AND t.i <= b.i)) AS c FROM {tag}_z a JOIN {tag}_z b ON a.i < b.i)")
    out.append(f"{tag}_d1 AS (SELECT e, c, 0 AS s FROM {tag}_c WHERE s = 0)")
    for q in range(2, kappa + 1):
        out.append(f"{tag}_d{q} AS (SELECT e, min(t) AS c, first(s ORDER BY t, s) AS s FROM (SELECT k.e, d.c + k.c AS t, k.s FROM {tag}_c k JOIN {tag}_d{q-1} d ON d.e = k.s) GROUP BY e)")
    out.append(f"{tag}_b{kappa} AS (SELECT max(i) AS e FROM {tag}_p)")
    for q in range(kappa - 1, 0, -1):
        out.append(f"{tag}_b{q} AS (SELECT s AS e FROM {tag}_d{q+1} WHERE e = (SELECT e FROM {tag}_b{q+1}))")
    union = " UNION ALL ".join(f"SELECT {q} AS q, e FROM {tag}_b{q}" for q in range(1, kappa + 1))
    out.append(f"{tag}_ends AS (SELECT q, u.e, p.x AS hi FROM ({union}) u JOIN {tag}_p p ON p.i = u.e)")
    return ", ".join(out)


def line(name: str, feature: str, kappa: int, p: int = 2, lam: float = 0.0) -> str:
    return f"WITH {line_ctes(matrix(name), feature, kappa, 'd', p, lam)} SELECT (q-1)::INT AS comp, hi, round((SELECT c FROM d_d{kappa} ORDER BY e DESC LIMIT 1), 4) AS cost FROM d_ends"


def encoders(name: str, features: dict[str, str], kappa: int) -> tuple[str, str, str]:
    """CTEs, the FROM clause, and the encoded columns over the joined rows."""
    ctes, joins, cols = [f"x AS MATERIALIZED {matrix(name)}"], ["x"], []
    for f, kind in features.items():
        if kind == "cat":
            ctes.append(f"r_{f} AS (SELECT {f} AS v, row_number() OVER (ORDER BY count(*) DESC, {f}) - 1 AS rk FROM x GROUP BY {f})")
            joins.append(f"JOIN r_{f} ON r_{f}.v = x.{f}")
            cols.append(f"least(r_{f}.rk, {kappa - 1})::INT AS c_{f}")
        else:
            ctes.append(line_ctes("x", f, kappa, f"l_{f}"))
            ctes.append(f"e_{f} AS (SELECT v.x AS v, (SELECT count(*) FROM l_{f}_ends WHERE hi < v.x) AS c FROM l_{f}_v v)")
            joins.append(f"JOIN e_{f} ON e_{f}.v = x.{f}")
            cols.append(f"e_{f}.c::INT AS c_{f}")
    return ", ".join(ctes), " ".join(joins), ", ".join(cols)


def grid(name: str, features: dict[str, str], kappa: int) -> str:
    ctes, joins, cols = encoders(name, features, kappa)
    keys = ", ".join(f"c_{f}" for f in features)
    return f"WITH {ctes} SELECT {keys}, count(*)::BIGINT AS w FROM (SELECT {cols} FROM {joins}) GROUP BY ALL"
