"""SQL twins of the training loop: one chain of common table expressions for each iteration."""

from __future__ import annotations

from .workloads import WORKLOADS

P = "(CASE WHEN {z} >= 0 THEN 1 / (1 + exp(-abs({z}))) ELSE exp(-abs({z})) / (1 + exp(-abs({z}))) END)"
COST = "(greatest({z}, 0) + ln(1 + exp(-abs({z}))) - {y} * {z})"


def rounded(x: str, digits: int) -> str:
    return f"(CASE WHEN round({x}, {digits}) = 0 THEN 0.0 ELSE round({x}, {digits}) END)"


def loop(name: str, iterations: int, alpha: float | None = None, rows: str | None = None) -> str:
    """WITH clause: e (all entries), tr (training part), te (test part) and, for each k, z, g and t as after iteration k; t0 is the start."""
    w = WORKLOADS[name]
    alpha = w.alpha if alpha is None else alpha
    out = [
        f"e AS MATERIALIZED ({rows or w.sql})",
        f"tr AS MATERIALIZED (SELECT * FROM e WHERE NOT ({w.test}) AND label IS NOT NULL)",
        f"te AS MATERIALIZED (SELECT * FROM e WHERE {w.test})",
        "t0 AS MATERIALIZED (SELECT DISTINCT f, 0.0::DOUBLE AS theta FROM tr)",
    ]
    for k in range(1, iterations + 1):
        out += [
            f"z{k} AS MATERIALIZED (SELECT sample_id, max(label) AS label, sum(x * theta) AS z FROM tr JOIN t{k - 1} USING (f) GROUP BY sample_id)",
            f"g{k} AS MATERIALIZED (SELECT f, sum(x * (p - y)) AS grad FROM tr JOIN (SELECT sample_id, label AS y, {P.format(z='z')} AS p FROM z{k}) USING (sample_id) GROUP BY f)",
            f"t{k} AS MATERIALIZED (SELECT f, theta - {alpha!r}::DOUBLE * coalesce(grad, 0) AS theta FROM t{k - 1} LEFT JOIN g{k} USING (f))",
        ]
    return "WITH " + ",\n".join(out)


def predictions(k: int, source: str = "te", name: str = "p") -> str:
    """A further expression: predictions at the weights after iteration k."""
    z = "coalesce(sum(x * theta), 0.0)"
    return f"{name} AS MATERIALIZED (SELECT sample_id, label, z, {P.format(z='z')} AS p1, (z >= 0)::INT AS predicted, known FROM (SELECT sample_id, max(label) AS label, {z} AS z, count(theta) AS known FROM {source} LEFT JOIN t{k} USING (f) GROUP BY sample_id))"


def scores(source: str = "p", keys: str = "") -> str:
    """(keys, class, precision, recall, f) of predictions."""
    comma, group = (f"{keys}, ", f" GROUP BY {keys}") if keys else ("", "")
    count = ", ".join(f"sum((label = {y} AND predicted = {p})::INT) AS {n}" for n, y, p in (("tp", 1, 1), ("fp", 0, 1), ("fn", 1, 0), ("tn", 0, 0)))
    return (
        f"SELECT {comma}class, pr AS precision, re AS recall, CASE WHEN pr + re = 0 THEN 0.0 ELSE 2 * pr * re / (pr + re) END AS f FROM ("
        f"SELECT {comma}class, CASE WHEN a + b = 0 THEN 0.0 ELSE a / (a + b)::DOUBLE END AS pr, CASE WHEN a + c = 0 THEN 0.0 ELSE a / (a + c)::DOUBLE END AS re FROM ("
        f"SELECT {comma}1 AS class, tp AS a, fp AS b, fn AS c FROM (SELECT {comma}{count} FROM {source} WHERE label IS NOT NULL{group}) "
        f"UNION ALL SELECT {comma}0, tn, fn, fp FROM (SELECT {comma}{count} FROM {source} WHERE label IS NOT NULL{group})))"
    )


def rounded_scores(inner: str, keys: str = "", digits: int = 9) -> str:
    comma = f"{keys}, " if keys else ""
    return f"SELECT {comma}class, {', '.join(f'round({c}, {digits}) AS {c}' for c in ('precision', 'recall', 'f'))} FROM ({inner})"


def history(iterations: int, tol: float, patience: int = 1, max_increase: float = 0.0, digits: int = 6) -> str:
    """Rows of the history after a ``loop`` of iterations + 1."""
    rows = " UNION ALL ".join(f"SELECT {k} AS iter, count(*)::BIGINT AS n, sum({COST.format(z='z', y='label')}) AS nll FROM z{k}" for k in range(1, iterations + 2))
    return (
        f"h AS (SELECT *, lag(nll) OVER (ORDER BY iter) AS before FROM ({rows})), "
        f"s AS (SELECT *, coalesce(nll > before * (1 + {max_increase!r}), false) AS diverged, CASE WHEN before IS NULL THEN 0 WHEN (before - nll) / greatest(1.0, before) < {tol!r} THEN 1 ELSE 0 END AS small FROM h) "
        f"SELECT iter, n, round(nll, {digits}) AS nll, round(nll / n, {digits}) AS mean_nll, round(before - nll, {digits}) AS delta, diverged, "
        f"(sum(small) OVER (ORDER BY iter ROWS BETWEEN {patience - 1} PRECEDING AND CURRENT ROW) >= {patience}) OR diverged AS stop FROM s"
    )
