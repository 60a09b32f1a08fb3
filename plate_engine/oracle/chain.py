"""DuckDB CTE chains for the inference queries, from the update equations and not from the message compiler.

One shape covers the coin, mixture, topic and sentence models: selector instances ``inst(d, i, n)`` with group d,
and child tables ``(d, i, v, m)`` of outcomes with multiplicities.
"""

from __future__ import annotations

from dataclasses import dataclass

from ..functions.special import digamma_sql


@dataclass
class Child:
    name: str
    sql: str
    beta: float
    dim: str
    per_group: bool = False


def lit(x: float) -> str:
    return f"{float(x)!r}::DOUBLE"


def vmp_chain(inst: str, children: list[Child], k: int, alpha: float, rounds: int, a: str = "d", b: str = "i", before: str = "", known: bool = False) -> str:
    """``WITH`` clause with th_t(d, k, g), <child>_t([d,] k, v, g), r_t(d, i, k, r, n), elbo_t(v) for t up to ``rounds``.

    With ``known``, ``inst`` has a column y: the selector's state where it is observed, else null."""
    ctes = [before] if before else []
    ctes.append(f"inst AS MATERIALIZED ({inst})")
    ctes += [f"{c.name} AS MATERIALIZED ({c.sql})" for c in children]
    y, given = (", y", lambda r: f"CASE WHEN y IS NULL THEN {r} ELSE CAST(y = k AS INTEGER)::DOUBLE END") if known else ("", lambda r: r)
    ctes.append(f"""r_0 AS MATERIALIZED (SELECT d, i, k, n, {given("u / sum(u) OVER (PARTITION BY d, i)")} AS r, 0e0 AS lse FROM
      (SELECT d, i, n, k{y}, CAST(1 + (31 * ({a}) + 17 * ({b}) + 7 * k) % 13 AS DOUBLE) AS u FROM inst, range({k}) t(k)))""")
    for t in range(rounds + 1):
        if t:
            p = t - 1
            iy = ", i.y" if known else ""
            parts = [f"SELECT i.d, i.i, e.k, i.n, e.e{iy} FROM inst i JOIN et_{p} e ON e.d = i.d"]
            for c in children:
                on = "e.d = c.d AND " if c.per_group else ""
                parts.append(f"SELECT i.d, i.i, e.k, i.n, c.m * e.e AS e{iy} FROM inst i JOIN {c.name} c ON c.d = i.d AND c.i = i.i JOIN e{c.name}_{p} e ON {on}e.v = c.v")
            ctes.append(f"s_{t} AS MATERIALIZED (SELECT d, i, k, n{y}, sum(e) AS s FROM ({' UNION ALL '.join(parts)}) GROUP BY ALL)")
            ctes.append(f"r_{t} AS MATERIALIZED (SELECT d, i, k, n, {given("exp(s - top) / z")} AS r, top + ln(z) AS lse FROM (SELECT *, sum(exp(s - top)) OVER (PARTITION BY d, i) AS z FROM (SELECT *, max(s) OVER (PARTITION BY d, i) AS top FROM s_{t})))")
            kls = [f"SELECT -sum(kl) AS v FROM kt_{p}", *[f"SELECT -sum(kl) AS v FROM k{c.name}_{p}" for c in children], f"SELECT sum(n * lse) / {k} AS v FROM r_{t}"]
            ctes.append(f"elbo_{t} AS (SELECT sum(v) AS v FROM ({' UNION ALL '.join(kls)}))")
        ctes.append(f"th_{t} AS MATERIALIZED (SELECT d, k, {lit(alpha)} + sum(n * r) AS g FROM r_{t} GROUP BY d, k)")
        ctes.append(f"et_{t} AS MATERIALIZED (SELECT d, k, g, {digamma_sql('g')} - {digamma_sql('tot')} AS e FROM (SELECT *, sum(g) OVER (PARTITION BY d) AS tot FROM th_{t}))")
        ctes.append(f"kt_{t} AS (SELECT lgamma(sum(g)) - lgamma({lit(alpha)} * {k}) + sum(lgamma({lit(alpha)}) - lgamma(g) + (g - {lit(alpha)}) * e) AS kl FROM et_{t} GROUP BY d)")
        for c in children:
            key = "d, k" if c.per_group else "k"
            pick = "r.d, r.k" if c.per_group else "r.k"
            ctes.append(f"{c.name}_{t} AS MATERIALIZED (SELECT {pick}, c.v, {lit(c.beta)} + sum(r.n * c.m * r.r) AS g FROM r_{t} r JOIN {c.name} c ON c.d = r.d AND c.i = r.i GROUP BY {pick}, c.v)")
            ctes.append(f"e{c.name}_{t} AS MATERIALIZED (SELECT {key}, v, g, tot, {digamma_sql('g')} - {digamma_sql('tot')} AS e FROM (SELECT *, sum(g) OVER w + (({c.dim}) - count(*) OVER w) * {lit(c.beta)} AS tot FROM {c.name}_{t} WINDOW w AS (PARTITION BY {key})))")
            ctes.append(f"k{c.name}_{t} AS (SELECT lgamma(any_value(tot)) - lgamma({lit(c.beta)} * ({c.dim})) + sum(lgamma({lit(c.beta)}) - lgamma(g) + (g - {lit(c.beta)}) * e) AS kl FROM e{c.name}_{t} GROUP BY {key})")
    return "WITH " + ",\n".join(ctes)
