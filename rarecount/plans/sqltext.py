"""Building blocks of the SQL that other engines run: the same samples, dictionaries and registers."""

from __future__ import annotations

import math

from ..operators.populations import SALT, poisson_top
from ..operators.sampling import bound
from ..sources.tables import WORKLOADS


def bits(digest: str, chunk: int) -> str:
    return f"('0x' || substr({digest}, {8 * chunk + 1}, 8))::BIGINT"


def digest(prefix: str, *cols: str) -> str:
    return "md5(concat_ws('|', '" + prefix + "', " + ", ".join(f"CAST({c} AS VARCHAR)" for c in cols) + "))"


def rank(h: str) -> str:
    return f"(CASE WHEN {h} = 0 THEN 33 ELSE 33 - length(bin({h})) END)::INTEGER"


def sample(name: str, q: float, k: int, q_res: float | None = None, salt: str = "s") -> str:
    w = WORKLOADS[name]
    return (
        f"s AS (SELECT v, ({bits('d', 1)} % {k})::INTEGER AS site, {bits('d', 2)} < {bound(q if q_res is None else q_res)} AS res FROM "
        f"(SELECT {w.value} AS v, {digest(salt, *w.ids)} AS d FROM {w.sql()}) WHERE v IS NOT NULL AND {bits('d', 0)} < {bound(q)})"
    )


LOCAL = "local AS (SELECT site, v, count(*) AS c, sum(res::BIGINT)::BIGINT AS c_res FROM s GROUP BY site, v)"
PROFILE = "prof AS (SELECT i, count(*) AS f FROM (SELECT count(*) AS i FROM s GROUP BY v) GROUP BY i)"
EVIDENCE = (
    "ev AS (SELECT sum(i * f)::BIGINT AS n, sum(f)::BIGINT AS d, coalesce(sum(f) FILTER (i = 1), 0)::BIGINT AS f1, "
    "coalesce(sum(f) FILTER (i = 2), 0)::BIGINT AS f2, sum(i * i * f)::BIGINT AS m2 FROM prof)"
)
RESAMPLE = (
    "res AS (SELECT count(*) AS d_res, count(*) FILTER (t = 1) AS f1_res FROM (SELECT sum(c_res) AS t FROM local GROUP BY v) WHERE t > 0)"
)


def everything(name: str) -> str:
    """The population as s, for full-scan queries."""
    w = WORKLOADS[name]
    return f"s AS (SELECT {w.value} AS v, 0 AS site, true AS res FROM {w.sql()} WHERE {w.value} IS NOT NULL)"


def population(name: str) -> str:
    w = WORKLOADS[name]
    return f"pop AS (SELECT count(*) AS rows_all FROM {w.sql()} WHERE {w.value} IS NOT NULL)"


def law_keys(table: str, key: str) -> list[str]:
    """CTEs up to us: two uniforms of each key of a table, p and z."""
    u = lambda j: f"({bits('g', j)} + 0.5::DOUBLE) / {float(1 << 32)!r}::DOUBLE"
    return [f"keys AS (SELECT DISTINCT {key} AS v FROM {table} WHERE {key} IS NOT NULL)", f"us AS (SELECT {u(0)} AS p, {u(1)} AS z FROM (SELECT {digest(SALT, 'v')} AS g FROM keys))"]


def poisson_profile(mean: float) -> list[str]:
    """CTEs up to prof: a key's count is the last one whose predecessors' probabilities sum up to its uniform at most."""
    p = f"exp(i * ln({mean!r}::DOUBLE) - {mean!r}::DOUBLE - lgamma(i + 1.0::DOUBLE))"
    return [
        f"law AS (SELECT i, coalesce(sum({p}) OVER (ORDER BY i ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS low FROM (SELECT unnest(range(0, {poisson_top(mean) + 1})) AS i))",
        "prof AS (SELECT i, count(*) AS f FROM us ASOF JOIN law ON us.p >= law.low WHERE i > 0 GROUP BY i)",
    ]


def zipf_profile(x: float, per_key: float) -> list[str]:
    i = f"greatest(1.0::DOUBLE, floor(n * {per_key!r}::DOUBLE / pow(ceil(z * n), {x!r}::DOUBLE)))::BIGINT"
    return [f"prof AS (SELECT i, count(*) AS f FROM (SELECT {i} AS i FROM us, (SELECT count(*)::DOUBLE AS n FROM keys)) GROUP BY i)"]


def tail_profile(x: float, most: int) -> list[str]:
    return [f"prof AS (SELECT i, count(*) AS f FROM (SELECT least({most + 1.0!r}::DOUBLE, floor(pow(z, {-x!r}::DOUBLE)))::BIGINT AS i FROM us) GROUP BY i)"]


def registers(b: int, seed: int = 0, source: str = "local") -> str:
    return (
        f"regs AS (SELECT site, reg, max(r) AS rd, coalesce(max(r) FILTER (c = 1), 0)::INTEGER AS r1 FROM (SELECT site, c, ({bits('d', 0)} % {1 << b})::INTEGER AS reg, "
        f"{rank(bits('d', 1))} AS r FROM (SELECT *, {digest(str(seed), 'v')} AS d FROM {source})) GROUP BY site, reg)"
    )


def word(digest: str) -> str:
    """The second 64 bits of a digest, as the counters of the second moment take them."""
    return f"('0x' || substr({digest}, 17, 16))::UBIGINT"


def moment(depth: int, width: int, source: str = "local") -> str:
    """m2: the median over lines of sums of squared counters, all bits from the values' one digest."""
    bits = 64 // depth
    part = f"((g >> (row * {bits})::UBIGINT) & {(1 << bits) - 1}::UBIGINT)"
    return (
        f"cells AS (SELECT row, ({part} >> 1::UBIGINT) % {width} AS bucket, sum((1 - 2 * ({part} & 1::UBIGINT)::BIGINT) * c)::BIGINT AS s FROM "
        f"(SELECT c, {word(digest('0', 'v'))} AS g FROM {source}), (SELECT unnest(range(0, {depth})) AS row) GROUP BY ALL), "
        "mom AS (SELECT median(sq) AS m2 FROM (SELECT sum(s::DOUBLE * s) AS sq FROM cells GROUP BY row))"
    )


STATE = (
    "ranked AS (SELECT *, row_number() OVER (PARTITION BY reg ORDER BY rd DESC, site) AS pos FROM regs), "
    "state AS (SELECT reg, max(rd) FILTER (pos = 1) AS m1, max(site) FILTER (pos = 1) AS owner, max(r1) FILTER (pos = 1) AS s_owner, "
    "coalesce(max(rd) FILTER (pos = 2), 0)::INTEGER AS m2 FROM ranked GROUP BY reg)"
)


def leave_one_out(b: int) -> str:
    m = 1 << b
    return (
        f"tot AS (SELECT coalesce(sum(pow(2.0::DOUBLE, -m1)), 0) + ({m} - count(*)) AS z, {m} - count(*) AS e FROM state), "
        "own AS (SELECT owner AS site, sum(pow(2.0::DOUBLE, -m2) - pow(2.0::DOUBLE, -m1)) AS dy, sum((m2 = 0)::BIGINT)::BIGINT AS ey, "
        "sum(pow(2.0::DOUBLE, -greatest(m2, s_owner)) - pow(2.0::DOUBLE, -m1)) AS dys, sum((greatest(m2, s_owner) = 0)::BIGINT)::BIGINT AS eys FROM state GROUP BY owner), "
        "loo AS (SELECT site, z + dy AS z_y, e + ey AS e_y, z + dys AS z_ys, e + eys AS e_ys FROM own, tot)"
    )


def classic(z: str, e: str, b: int) -> str:
    m = 1 << b
    alpha = 0.7213 / (1 + 1.079 / m)
    raw = f"({alpha * m * m!r}::DOUBLE / {z})"
    return f"CASE WHEN {raw} <= {2.5 * m!r} THEN CASE WHEN {e} > 0 THEN {m} * ln({m} / {e}::DOUBLE) ELSE {raw} END ELSE {raw} END"


def f1_classic(b: int) -> str:
    """Everything from registers to the total of terms."""
    return (
        f"{STATE}, {leave_one_out(b)}, f1 AS (SELECT coalesce(sum(({classic('z_ys', 'e_ys', b)}) - ({classic('z_y', 'e_y', b)})), 0) AS f1_hat FROM loo)"
    )


def smooth(z: str, e: str, b: int) -> str:
    m = 1 << b
    x = f"({e}::DOUBLE / {m})"
    steps = f"list_reduce(list_prepend([{x}, {x}, 0.5::DOUBLE], list_transform(range(0, {b + 8}), lambda i: [0.0::DOUBLE, 0.0::DOUBLE, 0.0::DOUBLE]))"
    tail = f"({steps}, lambda a, i: [a[1] * a[1], a[2] + a[1] * a[1] * (a[3] * 2), a[3] * 2]))[2]"
    return f"CASE WHEN {e} >= {m} THEN 0 ELSE {m * m / (2 * math.log(2))!r}::DOUBLE / ({z} - {e} + {m} * {tail}) END"


ESTIMATES = {"classic": classic, "smooth": smooth}


def f1_all_registers(b: int, estimator: str = "classic", regs: str = "regs", out: str = "f1") -> str:
    """The definition, with no shortcut: for each site the union of all others, with and without its own
    singletons, over all registers; then the sum of the differences of estimates."""
    m, est = 1 << b, ESTIMATES[estimator]
    return (
        f"{out}_y AS (SELECT j.site, r.reg, max(r.rd) AS y FROM (SELECT DISTINCT site FROM {regs}) j JOIN {regs} r ON r.site <> j.site GROUP BY ALL), "
        f"{out}_x AS (SELECT coalesce(o.site, r.site) AS site, coalesce(y, 0) AS y, greatest(coalesce(y, 0), coalesce(r1, 0)) AS ys FROM {out}_y o FULL JOIN {regs} r ON o.site = r.site AND o.reg = r.reg), "
        f"{out}_z AS (SELECT site, sum(pow(2.0::DOUBLE, -y)) + ({m} - count(*)) AS z_y, {m} - count(*) FILTER (y > 0) AS e_y, "
        f"sum(pow(2.0::DOUBLE, -ys)) + ({m} - count(*)) AS z_ys, {m} - count(*) FILTER (ys > 0) AS e_ys FROM {out}_x GROUP BY site), "
        f"{out} AS (SELECT coalesce(sum(({est('z_ys', 'e_ys', b)}) - ({est('z_y', 'e_y', b)})), 0) AS f1_hat FROM {out}_z)"
    )


def f1_direct(b: int, estimator: str = "classic", regs: str = "regs", out: str = "f1") -> str:
    """The same where there are many sites: a site's union of others differs from the whole union only in registers that
    the site has itself, so only those are merged anew, each from all other sites."""
    m, est = 1 << b, ESTIMATES[estimator]
    return (
        f"{out}_u AS (SELECT reg, max(rd) AS u FROM {regs} GROUP BY reg), "
        f"{out}_w AS (SELECT sum(pow(2.0::DOUBLE, -u)) + ({m} - count(*)) AS z, {m} - count(*) AS e FROM {out}_u), "
        f"{out}_y AS (SELECT a.site, a.reg, any_value(a.r1) AS r1, coalesce(max(o.rd), 0) AS y FROM {regs} a LEFT JOIN {regs} o ON a.reg = o.reg AND a.site <> o.site GROUP BY a.site, a.reg), "
        f"{out}_z AS (SELECT site, any_value(z) + sum(pow(2.0::DOUBLE, -y) - pow(2.0::DOUBLE, -u)) AS z_y, any_value(e) + count(*) FILTER (y = 0) AS e_y, "
        f"any_value(z) + sum(pow(2.0::DOUBLE, -greatest(y, r1)) - pow(2.0::DOUBLE, -u)) AS z_ys, any_value(e) + count(*) FILTER (greatest(y, r1) = 0) AS e_ys "
        f"FROM {out}_y JOIN {out}_u USING (reg), {out}_w GROUP BY site), "
        f"{out} AS (SELECT coalesce(sum(({est('z_ys', 'e_ys', b)}) - ({est('z_y', 'e_y', b)})), 0) AS f1_hat FROM {out}_z)"
    )


def sketched(
    name: str, q: float, k: int, b: int, depth: int = 3, width: int = 20_000, estimator: str = "smooth", direct: bool = False, source: list[str] | None = None
) -> list[str]:
    """CTEs up to sk: n, d, f1, m2, d_res, f1_res and rows_all, all sketched values by their definitions.

    ``source``: CTEs of the sample s and the population pop, if they aren't a table's."""
    m, est = 1 << b, ESTIMATES[estimator]
    out = [*source, LOCAL] if source else [sample(name, q, k), LOCAL, population(name)]
    for suffix, count in (("", "c"), ("_res", "c_res")):
        source = f"(SELECT site, v, {count} AS c FROM local WHERE {count} > 0)"
        out.append(registers(b, 0, source).replace("regs AS", f"regs{suffix} AS", 1))
        out.append((f1_direct if direct else f1_all_registers)(b, estimator, f"regs{suffix}", f"f1{suffix}"))
        out.append(f"u{suffix} AS (SELECT sum(pow(2.0::DOUBLE, -r)) + ({m} - count(*)) AS z, {m} - count(*) AS e FROM (SELECT reg, max(rd) AS r FROM regs{suffix} GROUP BY reg))")
        out.append(f"d{suffix} AS (SELECT {est('z', 'e', b)} AS d_hat FROM u{suffix})")
    out.append(moment(depth, width))
    clamp = lambda x: f"(SELECT greatest(0, least(f1_hat, d_hat)) FROM f1{x}, d{x})"
    out.append(
        f"sk AS (SELECT (SELECT count(*) FROM s) AS n, (SELECT d_hat FROM d) AS d, {clamp('')} AS f1, (SELECT m2 FROM mom) AS m2, "
        f"(SELECT d_hat FROM d_res) AS d_res, {clamp('_res')} AS f1_res, (SELECT rows_all FROM pop) AS rows_all)"
    )
    return out
