"""The same samples and estimates as relational SQL, one chain of named tables each, for DuckDB.

Nothing here is used to compute results; the texts state them a second time, independently.
"""

from __future__ import annotations

from seedrank.plans.workloads import WORKLOADS

INF = "CAST('Infinity' AS DOUBLE)"


def cdf(family: str, w: str, x: str) -> str:
    value = f"least(1.0, ({w}) * ({x}))" if family == "ipps" else f"1 - exp(-(({w}) * ({x})))"
    return f"(CASE WHEN ({w}) > 0 THEN {value} ELSE 0.0 END)"


def uniform(*parts: str) -> str:
    return f"((CAST('0x' || substr(md5(concat_ws('|', {', '.join(parts)})), 1, 13) AS BIGINT) + 0.5) / 4503599627370496.0)"


def rank_of(family: str, w: str, u: str) -> str:
    return f"({u}) / ({w})" if family == "ipps" else f"-ln(1.0 - ({u})) / ({w})"


def _in(names) -> str:
    return "(" + ", ".join(f"'{n}'" for n in names) + ")"


def ranked(workload: str, names, family="ipps", joint="shared", salt="v1", runs=1, unit=False) -> str:
    """Tables ``w`` and ``ranked``."""
    keep = f" WHERE assignment IN {_in(names)}" if names else ""
    s = f"'{salt}#' || CAST(run AS VARCHAR)"
    weight = "1.0" if unit else "CAST(weight AS DOUBLE)"
    base = f"w AS (SELECT * FROM ({WORKLOADS[workload].sql}){keep}),\nruns AS (SELECT unnest(range(0, {runs})) AS run),\n"
    if joint == "inddiff":
        gap = "weight - coalesce(lag(weight) OVER (PARTITION BY run, key ORDER BY weight, assignment), 0)"
        level = "CAST(row_number() OVER (PARTITION BY run, key ORDER BY weight, assignment) - 1 AS VARCHAR)"
        u = uniform(s, "'gap'", "level", "key")
        return base + (
            f"gaps AS (SELECT run, assignment, key, CAST(weight AS DOUBLE) AS weight, CAST({gap} AS DOUBLE) AS gap, {level} AS level FROM w, runs WHERE weight > 0),\n"
            f"d AS (SELECT *, CASE WHEN gap > 0 THEN {rank_of('exp', 'gap', u)} ELSE {INF} END AS draw FROM gaps),\n"
            "ranked AS (SELECT run, assignment, key, weight, CAST(NULL AS DOUBLE) AS seed, weight AS value, min(draw) OVER (PARTITION BY run, key ORDER BY weight, assignment ROWS UNBOUNDED PRECEDING) AS rank FROM d)"
        )
    seed = uniform(s, "key") if joint == "shared" else uniform(s, "assignment", "key")
    return base + (
        f"s AS (SELECT run, assignment, key, {weight} AS weight, CAST(weight AS DOUBLE) AS value, {seed} AS seed FROM w, runs WHERE weight > 0),\n"
        f"ranked AS (SELECT *, {rank_of(family, 'weight', 'seed')} AS rank FROM s)"
    )


def bottom_k(k) -> str:
    """Tables ``ent`` (with ``member``) and ``meta`` from ``ranked``; ``k``: a number or a map."""
    own = str(k) if not isinstance(k, dict) else "CASE assignment " + " ".join(f"WHEN '{b}' THEN {n}" for b, n in k.items()) + " END"
    return (
        f"place AS (SELECT *, row_number() OVER (PARTITION BY run, assignment ORDER BY rank, key) AS pos, {own} AS k FROM ranked),\n"
        "ent AS (SELECT *, pos <= k AS member FROM place WHERE pos <= k + 1),\n"
        f"meta AS (SELECT run, assignment, coalesce(max(CASE WHEN pos = k THEN rank END), {INF}) AS rk, coalesce(max(CASE WHEN pos = k + 1 THEN rank END), {INF}) AS rk1 FROM ent GROUP BY 1, 2)"
    )


def ipps_tau(k: int) -> str:
    """Table ``tau`` from ``w``."""
    return (
        "tot AS (SELECT assignment, sum(CAST(weight AS DOUBLE)) AS total, count(*) AS n FROM w WHERE weight > 0 GROUP BY 1),\n"
        "heavy AS (SELECT assignment, weight, row_number() OVER (PARTITION BY assignment ORDER BY weight DESC, key) AS j, "
        "sum(CAST(weight AS DOUBLE)) OVER (PARTITION BY assignment ORDER BY weight DESC, key ROWS UNBOUNDED PRECEDING) AS upto FROM w WHERE weight > 0),\n"
        f"step AS (SELECT assignment, j, ({k} - j + 1) / (total - upto + weight) AS tau, weight FROM heavy JOIN tot USING (assignment) WHERE j <= {k}),\n"
        "first AS (SELECT assignment, arg_min(tau, j) AS tau FROM step WHERE weight * tau <= 1 GROUP BY 1),\n"
        f"tau AS (SELECT assignment, CASE WHEN n <= {k} THEN {INF} ELSE tau END AS tau FROM tot LEFT JOIN first USING (assignment))"
    )


def poisson() -> str:
    """Tables ``ent`` and ``meta`` from ``ranked`` and ``tau``."""
    return (
        "ent AS (SELECT r.*, true AS member FROM ranked r JOIN tau USING (assignment) WHERE rank < tau),\n"
        "meta AS (SELECT run, assignment, tau AS rk, tau AS rk1 FROM tau, (SELECT DISTINCT run FROM ranked))"
    )


def dispersed_cells(names, value: str = "weight") -> str:
    """Tables ``cells`` and ``o`` (with the least threshold and the order by weight) of sampled keys."""
    bs = ", ".join(f"('{b}')" for b in names)
    return (
        f"ks AS (SELECT DISTINCT run, key FROM ent WHERE member AND assignment IN {_in(names)}),\n"
        f"cells AS (SELECT ks.run, ks.key, b.b, coalesce(e.{value}, 0.0) AS w, coalesce(e.rank, {INF}) AS rank, e.seed, e.key IS NOT NULL AS inn, "
        f"coalesce(CASE WHEN e.key IS NOT NULL THEN m.rk1 ELSE m.rk END, {INF}) AS theta FROM ks CROSS JOIN (VALUES {bs}) b(b) "
        "LEFT JOIN (SELECT * FROM ent WHERE member) e ON e.run = ks.run AND e.key = ks.key AND e.assignment = b.b LEFT JOIN meta m ON m.run = ks.run AND m.assignment = b.b),\n" + _ordered()
    )


def full_cells(names, value: str = "weight") -> str:
    """The same of all keys, with every weight known."""
    bs = ", ".join(f"('{b}')" for b in names)
    return (
        "ks AS (SELECT DISTINCT run, key FROM ranked),\n"
        f"c0 AS (SELECT ks.run, ks.key, b.b, coalesce(e.{value}, 0.0) AS w, coalesce(e.rank, {INF}) AS rank, e.seed, coalesce(m.rk, {INF}) AS rk, coalesce(m.rk1, {INF}) AS rk1 FROM ks CROSS JOIN (VALUES {bs}) b(b) "
        "LEFT JOIN ranked e ON e.run = ks.run AND e.key = ks.key AND e.assignment = b.b LEFT JOIN meta m ON m.run = ks.run AND m.assignment = b.b),\n"
        "cells AS (SELECT run, key, b, w, rank, seed, rank < rk1 AS inn, CASE WHEN rank < rk1 THEN rk1 ELSE rk END AS theta FROM c0),\n" + _ordered()
    )


def _ordered() -> str:
    return "o AS (SELECT *, min(theta) OVER (PARTITION BY run, key) AS mt, row_number() OVER (PARTITION BY run, key ORDER BY w DESC, b) AS wr, max(seed) OVER (PARTITION BY run, key) AS u FROM cells)"


def s_set(ell: int, family: str, joint: str, f: str = "bar") -> str:
    """Table ``adj`` from ``o``."""
    p = cdf(family, "bar", "mt") if joint != "independent" else "pp"
    return (
        f"g AS (SELECT run, key, max(mt) AS mt, count(*) FILTER (WHERE rank < mt) AS n, max(CASE WHEN wr = {ell} THEN w END) AS bar, max(w) AS mx, min(w) AS mn, product({cdf(family, 'w', 'mt')}) AS pp FROM o GROUP BY 1, 2),\n"
        f"adj AS (SELECT run, key, {f} AS f, {p} AS p, ({f}) / {p} AS adjusted FROM g WHERE n >= {ell} AND ({f}) <> 0)"
    )


def l_set(ell: int, m: int, family: str, joint: str, salt: str = "v1") -> str:
    seed = "u" if joint == "shared" else uniform(f"'{salt}#' || CAST(o.run AS VARCHAR)", "b", "o.key")
    bounded = "true" if ell == m else f"bool_and(wr <= {ell} OR {seed} < {cdf(family, 'bar', 'theta')})"
    each = cdf(family, f"CASE WHEN wr <= {ell} THEN w ELSE bar END", "theta")
    p = f"product({each})" if joint == "independent" else f"min({each})"
    return (
        f"bars AS (SELECT run, key, max(CASE WHEN wr = {ell} THEN w END) AS bar, count(*) FILTER (WHERE inn) AS n FROM o GROUP BY 1, 2),\n"
        f"g AS (SELECT o.run, o.key, max(bar) AS bar, max(n) AS n, {bounded} AS bounded, {p} AS p FROM o JOIN bars USING (run, key) GROUP BY 1, 2),\n"
        f"adj AS (SELECT run, key, bar AS f, p, bar / p AS adjusted FROM g WHERE n >= {ell} AND bounded AND bar <> 0)"
    )


def inclusive(family: str, joint: str, f: str, where: str = "any_in") -> str:
    """Table ``adj`` from ``o`` of full cells; ``f`` over mx, mn or w_<name>."""
    each = cdf(family, "w", "theta")
    p = {"shared": f"max({each})", "independent": f"1 - product(1 - {each})", "inddiff": "1 - exp(-sum(CASE WHEN gap > 0 THEN gap * reach ELSE 0 END))"}[joint]
    return (
        "asc_ AS (SELECT *, w - coalesce(lag(w) OVER (PARTITION BY run, key ORDER BY wr DESC), 0) AS gap, max(theta) OVER (PARTITION BY run, key ORDER BY wr DESC ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS reach FROM o),\n"
        f"g AS (SELECT run, key, max(w) AS mx, min(w) AS mn, bool_or(inn) AS any_in, map_from_entries(list((b, w))) AS v, {p} AS p, max(mt) AS mt, min(rank) AS mr FROM asc_ GROUP BY 1, 2),\n"
        f"adj AS (SELECT run, key, {f} AS f, p, ({f}) / p AS adjusted FROM g WHERE {where} AND ({f}) <> 0)"
    )


def generic(family: str, f: str) -> str:
    return (
        "g AS (SELECT run, key, max(w) AS mx, min(w) AS mn, max(mt) AS mt, min(rank) AS mr, bool_or(inn) AS any_in FROM o GROUP BY 1, 2),\n"
        f"adj AS (SELECT run, key, {f} AS f, {cdf(family, 'mx', 'mt')} AS p, ({f}) / {cdf(family, 'mx', 'mt')} AS adjusted FROM g WHERE any_in AND mr <= mt AND ({f}) <> 0)"
    )


def chain(*tables: str, select: str) -> str:
    return "WITH " + ",\n".join(tables) + "\n" + select


ROWS = "SELECT run, key, round(f, 4) AS f, round(p, 9) AS p, round(adjusted, 3) AS adjusted FROM adj"


def sweep(tag: str, workload: str, names, ks, family="ipps", joint="shared", runs=25, unit=False) -> list[str]:
    """Tables <tag>p (places of the smallest ranks) and <tag>e (keys with weights, thresholds and probabilities for each size)."""
    s = "'v1#' || CAST(run AS VARCHAR)"
    seed = uniform(s, "key") if joint == "shared" else uniform(s, "assignment", "key")
    of = lambda b, x, none: f"coalesce(max(CASE WHEN assignment = '{b}' THEN {x} END), {none})"
    m, sizes = range(len(names)), ", ".join(f"({k})" for k in ks)
    th = lambda b, step: f"coalesce(max(CASE WHEN assignment = '{b}' AND pos = k{step} THEN rank END), {INF})"
    return [
        f"{tag}w AS (SELECT assignment, key, CAST(weight AS DOUBLE) AS weight FROM ({WORKLOADS[workload].sql}) WHERE assignment IN {_in(names)} AND weight > 0)",
        f"{tag}r AS MATERIALIZED (SELECT run, assignment, key, weight, {rank_of(family, '1.0' if unit else 'weight', seed)} AS rank FROM {tag}w, (SELECT unnest(range(0, {runs})) AS run))",
        f"{tag}p AS MATERIALIZED (SELECT run, assignment, key, rank, row_number() OVER (PARTITION BY run, assignment ORDER BY rank, key) AS pos FROM {tag}r QUALIFY pos <= {max(ks) + 1})",
        f"{tag}t AS (SELECT k, run, {', '.join(f'{th(b, x)} AS {n}{i}' for i, b in enumerate(names) for n, x in (('lo', ''), ('hi', ' + 1')))} FROM {tag}p, (VALUES {sizes}) z(k) GROUP BY 1, 2)",
        f"{tag}f AS (SELECT run, key, {', '.join(f'{of(b, x, none)} AS {n}{i}' for i, b in enumerate(names) for n, x, none in (('w', 'weight', '0.0'), ('r', 'rank', INF)))} FROM {tag}r GROUP BY 1, 2)",
        f"{tag}c AS (SELECT run, k, {', '.join(f'w{i}, CASE WHEN r{i} < hi{i} THEN hi{i} ELSE lo{i} END AS t{i}' for i in m)} FROM {tag}f JOIN {tag}t USING (run))",
        f"{tag}e AS (SELECT *, {', '.join(cdf(family, f'w{i}', f't{i}') + f' AS e{i}' for i in m)} FROM {tag}c)",
    ]


def _measure(kind: str, at: list[int], family: str, joint: str) -> tuple[str, str]:
    """The function of a key and the variance of its adjusted value, over the columns of a sweep."""
    each = lambda c: [f"{c}{i}" for i in at]
    of = lambda fn, c: f"{fn}({', '.join(each(c))})" if len(at) > 1 else each(c)[0]
    high, low, near = of("greatest", "w"), of("least", "w"), of("least", "t")
    every = "(" + " * ".join(each("e")) + ")" if joint == "independent" else of("least", "e")
    any_ = "(1 - " + " * ".join(f"(1 - e{i})" for i in at) + ")" if joint == "independent" else of("greatest", "e")
    if kind in ("l1_l", "l1_s"):
        ph, pl = cdf(family, high, near), every if kind == "l1_l" else cdf(family, low, near)
        both = f"(CASE WHEN {low} > 0 THEN {pl} ELSE 0 END)"
        gap = f"({high} / {ph} - CASE WHEN {low} > 0 THEN {low} / {pl} ELSE 0 END)"
        return f"({high} - {low})", f"CASE WHEN {high} > 0 THEN {both} * {gap} * {gap} + ({ph} - {both}) * ({high} / {ph}) * ({high} / {ph}) - ({high} - {low}) * ({high} - {low}) ELSE 0 END"
    if kind.startswith(("plain_", "inclusive_")) and kind.rpartition("_")[2].isdigit():
        i = at[int(kind.rpartition("_")[2])]
        f, p = f"w{i}", f"e{i}" if kind.startswith("plain") else any_
    else:
        f, p = {
            "min_l": (low, every), "min_s": (low, cdf(family, low, near)), "max": (high, cdf(family, high, near)), "inclusive_max": (high, any_),
            "unweighted_max": (high, cdf(family, "1.0", near)), "unweighted_min": (low, cdf(family, "1.0", near)),
        }[kind]
    return f, f"CASE WHEN {f} > 0 THEN {f} * {f} * (1 / {p} - 1) ELSE 0 END"


def sweep_sums(tag: str, names, columns, family="ipps", joint="shared") -> str:
    """Table <tag>s: for each (measure, names) the sum of variances v<j> and that of the function f<j>, by size."""
    parts = []
    for j, (kind, part) in enumerate(columns):
        f, v = _measure(kind, [list(names).index(b) for b in part], family, joint)
        parts += [f"sum({v}) AS v{j}", f"sum({f}) AS f{j}"]
    means = ", ".join(f"avg({x}{j}) AS {x}{j}" for j in range(len(columns)) for x in "vf")
    return f"{tag}s AS (SELECT k, {means} FROM (SELECT run, k, {', '.join(parts)} FROM {tag}e GROUP BY 1, 2) GROUP BY 1)"


def sweep_sizes(tag: str, ks) -> str:
    """Table <tag>z: distinct keys of all samples, by size."""
    sizes = ", ".join(f"({k})" for k in ks)
    return f"{tag}z AS (SELECT k, avg(n) AS keys FROM (SELECT k, run, count(DISTINCT key) AS n FROM {tag}p, (VALUES {sizes}) z(k) WHERE pos <= k GROUP BY 1, 2) GROUP BY 1)"
