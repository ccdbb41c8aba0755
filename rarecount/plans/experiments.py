"""The published experiments as queries: errors by sketch size, singletons at scale, communication, routes and the choice of one.

Samples of generated populations are drawn from digests, so that SQL engines draw the same ones. Populations of 10^11 rows and more
are never drawn row by row: the two best hashes of each register follow from the number of values alone.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import estimators as E
from ..functions.hashing import TWO32, keyed, md5_bits
from ..operators import analysis as A
from ..operators import metrics as M
from ..operators import populations as L
from ..operators import profile as P
from ..operators import sampling as S
from ..operators import singletons as G
from ..operators import summary as Y
from ..sources.tables import table
from . import sqltext as Q
from .queries import CHECKED, KEY, KEYED, MAIN, POISSON, RATE, ZIPF, accuracy, accuracy_sql, by_site, c, evidence, grid, grid_sql, population, population_keys, register, regs, rounded, sampled, sketched, sql_evidence, values, with_

COLUMNS = ("orderkey", "totalprice", "revenue")
#: The published setting: machines, sample rate, sketch sizes.
MACHINES, LOW_RATE, SIZES = 1024, 0.01, (10, 14, 18)
#: Generated populations: kind and parameter.
DATA = [(f"poisson_{m}", "poisson", float(m)) for m in POISSON] + [(f"zipf_{x}", "zipf", x) for x in ZIPF]
#: Values of a generated population for each row of ``part``; sampled counts told apart by inversion.
PER_PART, STEPS = 10, 40

# Generated samples ----------------------------------------------------------------------------------


def occurrences(r: Column, kind: str, x: float, distinct: Column) -> Column:
    """Expected rows of the r-th value: the mean of a Poisson law, or a power of the rank, 1 at least."""
    if kind == "poisson":
        return F.lit(x)
    return F.greatest(F.lit(1.0), F.floor(20.0 * distinct / F.pow(r.cast("double"), F.lit(x))).cast("double"))


def drawn_counts(values: DataFrame) -> DataFrame:
    """(v, c) of (v, m, u): a Poisson count of mean m by inversion of one uniform, up to ``STEPS``; above a mean of 12, the mean itself. Zeros are left out."""

    def draw(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            v, m, u, p = (batch.column(i).to_numpy() for i in range(4))
            c = np.where(m > 12, np.floor(m + 0.5), 0).astype(np.int64)
            # A step is made for those values only whose uniform is no less than the sum so far.
            at = np.flatnonzero((m <= 12) & (u >= p))
            p, m, u = p[at], m[at], u[at]
            cdf = p
            for i in range(1, STEPS + 1):
                c[at] = i
                p = p * m / i
                cdf = cdf + p
                on = u >= cdf
                at, p, m, u, cdf = at[on], p[on], m[on], u[on], cdf[on]
                if not len(at):
                    break
            some = c > 0
            yield pa.RecordBatch.from_arrays([pa.array(v[some]), pa.array(c[some])], names=["v", "c"])

    return values.select("v", "m", "u", F.exp(-c("m")).alias("p")).mapInArrow(draw, "v long, c long")


def generated(spark: SparkSession, sf: str, kind: str, x: float, q: float = LOW_RATE, k: int = MACHINES, keyed_by_part: bool = False) -> tuple[DataFrame, DataFrame]:
    """The tagged sample of a generated population, and one row rows_all, truth.

    Values are numbers, or ten variants of each row of ``part`` by its key, whose order is their rank."""
    distinct = table(spark, sf, "part").agg((F.count("*") * PER_PART).alias("distinct"))
    n = distinct.first()["distinct"]  # one number, for the range of values
    r = spark.range(1, n + 1).select(c("id").alias("v"))
    if keyed_by_part:
        variants = F.explode(F.sequence(F.lit(1), F.lit(PER_PART)))
        r = table(spark, sf, "part").select("p_partkey", variants.alias("j")).select((c("p_partkey") * PER_PART + c("j")).alias("v"))
    mean = occurrences(c("v"), kind, x, F.lit(float(n)))
    u = md5_bits(F.md5(keyed(f"{kind}{x}", c("v"))), 0) / float(TWO32)
    some = drawn_counts(r.select("v", (mean * q).alias("m"), u.alias("u")))
    d = F.md5(keyed("o", c("v"), c("o")))
    rows = some.select("v", F.explode(F.sequence(F.lit(1).cast("long"), c("c"))).alias("o")).select("v", d.alias("d"))
    sample = rows.select("v", (md5_bits(c("d"), 1) % k).cast("int").alias("site"), (md5_bits(c("d"), 2) < S.bound(q)).alias("res"))
    # Each machine has its own rows, as in files of its own; setting this up is not part of the method.
    sample = sample.repartition("site")
    return sample, r.agg(F.sum(mean).cast("long").alias("rows_all"), F.count("*").alias("truth"))


def generated_sql(kind: str, x: float, q: float = LOW_RATE, k: int = MACHINES, keyed_by_part: bool = False) -> list[str]:
    number = f"(SELECT count(*) * {PER_PART} FROM part)"
    mean = f"{x!r}::DOUBLE" if kind == "poisson" else f"greatest(1.0::DOUBLE, floor(20.0::DOUBLE * n / pow(v::DOUBLE, {x!r}::DOUBLE)))"
    values = f"(SELECT n, unnest(range(1, n + 1)) AS v FROM (SELECT {number} AS n))"
    if keyed_by_part:
        values = f"(SELECT n, p_partkey * {PER_PART} + j AS v FROM part, (SELECT unnest(range(1, {PER_PART + 1})) AS j), (SELECT {number} AS n))"
    start, steps = "[exp(-m), exp(-m), 0.0::DOUBLE, 0.0::DOUBLE]", f"list_transform(range(0, {STEPS}), lambda i: [0.0::DOUBLE, 0.0::DOUBLE, 0.0::DOUBLE, 0.0::DOUBLE])"
    fold = f"list_reduce(list_prepend({start}, {steps}), lambda a, i: [a[1] * m / (a[4] + 1), a[2] + a[1] * m / (a[4] + 1), a[3] + (u >= a[2])::INTEGER, a[4] + 1])[3]"
    return [
        f"means AS (SELECT v, {mean} AS i, {mean} * {q!r}::DOUBLE AS m, {Q.bits(Q.digest(f'{kind}{x}', 'v'), 0)} / {float(TWO32)!r}::DOUBLE AS u FROM {values})",
        f"counts AS (SELECT v, CASE WHEN m > 12 THEN round(m) ELSE {fold} END::BIGINT AS c FROM means)",
        f"s AS (SELECT v, ({Q.bits('d', 1)} % {k})::INTEGER AS site, {Q.bits('d', 2)} < {S.bound(q)} AS res FROM (SELECT v, {Q.digest('o', 'v', 'o')} AS d FROM (SELECT v, unnest(range(1, c + 1)) AS o FROM counts WHERE c > 0)))",
        "pop AS (SELECT sum(i)::BIGINT AS rows_all FROM means)",
    ]


# Errors of estimators by sketch size ----------------------------------------------------------------


def _errors_columns(s: SparkSession, d: str) -> DataFrame:
    out = None
    for name in COLUMNS:
        one = accuracy(s, d, name, SIZES, LOW_RATE, MACHINES)
        out = one if out is None else out.unionByName(one)
    return out


def _errors_generated(s: SparkSession, d: str) -> DataFrame:
    out = None
    for name, kind, x in DATA:
        sample, whole = generated(s, d, kind, x, keyed_by_part=True)
        rows_all, truth = F.broadcast(whole.select("rows_all")), whole.select("truth")
        sk = Y.sketched_evidence(sample, list(SIZES), hashing=CHECKED).crossJoin(rows_all)
        ex = P.evidence_of_counts(P.dictionary(sample)).crossJoin(rows_all)
        one = grid(s, sk, ex, truth).select(F.lit(name).alias("col"), "*")
        out = one if out is None else out.unionByName(one)
    return out


register("errors_by_size_columns", _errors_columns, " UNION ALL ".join(accuracy_sql(n, b, LOW_RATE, MACHINES, direct=True) for n in COLUMNS for b in SIZES))
register(
    "errors_by_size_generated",
    _errors_generated,
    " UNION ALL ".join(grid_sql(Q.sketched("", 0, 0, b, direct=True, source=generated_sql(kind, x, keyed_by_part=True)), name, b, f"SELECT count(*) * {PER_PART} FROM part", True) for name, kind, x in DATA for b in SIZES),
)


def _shares(s: SparkSession, d: str) -> DataFrame:
    """f1 / d of the three columns at one per cent: of the sample, and as expected from all rows."""
    out = None
    for name in COLUMNS:
        e = evidence(s, d, name, LOW_RATE).select("f1", "d", F.round(c("f1") / c("d"), 6).alias("share"))
        row = e.crossJoin(F.broadcast(A.c_at(P.exact_profile(values(s, d, name)), [LOW_RATE]).select(c("c").alias("expected")))).select(F.lit(name).alias("col"), "*")
        out = row if out is None else out.unionByName(row)
    return out


def _shares_sql(name: str) -> str:
    expected = with_(Q.everything(name), Q.PROFILE, select=f"SELECT round(sum(f * i * {LOW_RATE!r}::DOUBLE * exp(-i * {LOW_RATE!r}::DOUBLE)) / sum(f * (1 - exp(-i * {LOW_RATE!r}::DOUBLE))), 6) FROM prof")
    return "SELECT * FROM (" + with_(*sql_evidence(name, LOW_RATE)[:4], select=f"SELECT '{name}' AS col, f1, d, round(f1 / d::DOUBLE, 6) AS share, ({expected}) AS expected FROM ev") + ")"


register("share_of_known_columns", _shares, " UNION ALL ".join(_shares_sql(n) for n in COLUMNS))

# Singletons at 10^11 rows and more ------------------------------------------------------------------

SCALES = (1e11, 5e11, 1e12)
BIG = 16
#: Multiplicities of a power law that are told apart; values above them are in the sample more than once for sure.
LINES = 200_000


def number_of_values(kind: str, x: float, rows: float) -> float:
    """Values of a population of so many rows: by the mean, or all ranks to which a power law gives a row."""
    return rows / x if kind == "poisson" else float(math.floor((rows / sum(n**-x for n in range(1, 100_001))) ** (1 / x)))


def expected_samples(keys: DataFrame, q: float = LOW_RATE) -> DataFrame:
    """(kind, data, rows_all, d, f1): expected numbers of the sample's values and singletons, rounded; at such sizes a draw differs by a few in 10^5.

    Each key of a table stands for an equal part of a population's values, all with the number of rows that the law gives the key. Null without keys."""
    law = lambda wanted: {name: x for name, kind, x in DATA if kind == wanted}
    profiles = L.poisson_profiles(keys, law("poisson")).unionByName(L.tail_profiles(keys, law("zipf"), LINES))
    sums = profiles.groupBy("data").agg(F.expr(f"sum(f * (1 - exp(-i * {q!r}d))) as d"), F.expr(f"sum(f * i * {q!r}d * exp(-i * {q!r}d)) as f1"))
    sizes = [(data, rows, number_of_values(kind, x, rows)) for data, kind, x in DATA for rows in SCALES]
    each = ", ".join(f"struct({at} as kind, '{data}' as data, {rows!r}d as rows_all, {number!r}d as number)" for at, (data, rows, number) in enumerate(sizes))
    wanted = keys.agg(F.count("*").cast("double").alias("n")).select("n", F.expr(f"inline(array({each}))"))
    part = lambda x: f"cast(round(try_divide(number * {x}, n)) as long) as {x}"
    return wanted.join(F.broadcast(sums), "data", "left").selectExpr("kind", "data", "rows_all", part("d"), part("f1"))


def expected_sample_sql(kind: str, x: float, rows: float, q: float = LOW_RATE) -> list[str]:
    part = lambda total: f"round({number_of_values(kind, x, rows)!r}::DOUBLE * sum({total}) / (SELECT count(*)::DOUBLE FROM keys))::BIGINT"
    select = f"SELECT {part(f'f * (1 - exp(-i * {q!r}::DOUBLE))')} AS d, {part(f'f * i * {q!r}::DOUBLE * exp(-i * {q!r}::DOUBLE)')} AS f1 FROM prof"
    return [*Q.law_keys(KEYED, KEY), *(Q.poisson_profile(x) if kind == "poisson" else Q.tail_profile(x, LINES)), f"counts AS ({select})"]


def register_states(counts: DataFrame, b: int = BIG, k: int = MACHINES) -> DataFrame:
    """(kind, slot, m1, owner, s_owner, m2) as d hashed values, of which f1 are singletons on one of k sites each, would leave them.

    Hashes of a register's values are points of a Poisson process, so the least ones are sums of exponential steps; the best rank
    is that of the least hash. Values seen more than once are taken to stand on two sites or more.
    """
    m = 1 << b
    bits = lambda digest, j: f"cast(conv(substr({digest}, {8 * j + 1}, 8), 16, 10) as long)"
    rank = lambda steps, n: f"if({n} > 0 and {steps} < {n} / {m}d, least(33, cast(floor(-log2({steps} * {m} / {n})) as int) + 1), 0)"
    key = "concat(data, '|', rows_all)"
    reg = counts.sparkSession.range(0, m, 1, 8).selectExpr("cast(id as int) as slot").crossJoin(F.broadcast(counts))
    h = reg.selectExpr("kind", "slot", "cast(d - f1 as double) as o", "cast(f1 as double) as f", f"md5(concat_ws('|', {key}, '0', slot)) as x", f"md5(concat_ws('|', {key}, '1', slot)) as y")
    e = h.selectExpr("kind", "slot", "o", "f", *[f"-ln(({bits('x', j)} + 1) / {float(TWO32 + 1)!r}d) as e{j}" for j in range(4)], *[f"{bits('y', j)} % {k} as a{j}" for j in range(2)])
    r = e.selectExpr("kind", "slot", "a0", f"{rank('e0', 'f')} as r1", f"if(a0 <> a1, {rank('(e0 + e1)', 'f')}, {rank('(e0 + e1 + e2)', 'f')}) as r2", f"{rank('e3', 'o')} as rest")
    r = r.selectExpr("kind", "slot", "a0", "r1", "greatest(r2, rest) as other", "r1 > greatest(r2, rest) as own").where("r1 > 0 or other > 0")
    return r.selectExpr("kind", "slot", "greatest(r1, other) as m1", "if(own, a0, -1L) as owner", "if(own, r1, 0) as s_owner", "if(own, other, greatest(r1, other)) as m2", "own")


def _at_scale(s: SparkSession, d: str) -> DataFrame:
    """(data, rows_all, d, f1, owned, ranks, f1_hat, err): error of the number of singletons by distribution and size."""
    counts = expected_samples(population_keys(s, d))
    states = register_states(counts)
    hat = Y.estimates(states.selectExpr(f"{BIG} as b", "kind", "slot", "m1", "owner", "s_owner", "m2", "0L as s")).selectExpr("kind", "round(term, -3) as f1_hat")
    sums = states.groupBy("kind").agg(F.expr("sum(cast(own as long)) as owned"), F.expr("sum(cast(m1 + m2 as long)) as ranks"))
    return counts.join(F.broadcast(hat), "kind", "left").join(F.broadcast(sums), "kind", "left").drop("kind").withColumn("err", F.expr("round(try_divide(abs(f1_hat - f1), f1), 4)"))


def java_double(x: float) -> str:
    """A power of ten, or five of it, as the JVM writes it."""
    e = int(math.log10(x) + 1e-9)
    return f"{x / 10**e:.1f}E{e}"


def _at_scale_sql(name: str, kind: str, x: float, rows: float) -> str:
    b, m, key = BIG, 1 << BIG, f"{name}|{java_double(rows)}"
    rank = lambda steps, n: f"(CASE WHEN {n} > 0 AND {steps} < {n} / {m}::DOUBLE THEN least(33, floor(-log2({steps} * {m} / {n})) + 1) ELSE 0 END)::INTEGER"
    parts = [
        *expected_sample_sql(kind, x, rows),
        f"h AS (SELECT d, f1, reg, {Q.digest(key + '|0', 'reg')} AS p, {Q.digest(key + '|1', 'reg')} AS t FROM counts, (SELECT unnest(range(0, {m})) AS reg))",
        "e AS (SELECT d::DOUBLE AS d, f1::DOUBLE AS f1, reg, " + ", ".join(f"-ln(({Q.bits('p', j)} + 1) / {float(TWO32 + 1)!r}::DOUBLE) AS e{j}" for j in range(4)) + ", " + ", ".join(f"{Q.bits('t', j)} % {MACHINES} AS a{j}" for j in range(2)) + " FROM h)",
        f"r AS (SELECT reg, a0, {rank('e0', 'f1')} AS r1, CASE WHEN a0 <> a1 THEN {rank('(e0 + e1)', 'f1')} ELSE {rank('(e0 + e1 + e2)', 'f1')} END AS r2, {rank('e3', '(d - f1)')} AS rest FROM e)",
        "state AS (SELECT reg, greatest(r1, r2, rest) AS m1, r1 > greatest(r2, rest) AS own, CASE WHEN own THEN a0 ELSE -1 END AS owner, CASE WHEN own THEN r1 ELSE 0 END AS s_owner, CASE WHEN own THEN greatest(r2, rest) ELSE greatest(r1, r2, rest) END AS m2 FROM r WHERE greatest(r1, r2, rest) > 0)",
        Q.leave_one_out(b),
        f"f AS (SELECT round(sum(({Q.smooth('z_ys', 'e_ys', b)}) - ({Q.smooth('z_y', 'e_y', b)})), -3) AS f1_hat FROM loo)",
    ]
    select = f"SELECT '{name}' AS data, {rows!r}::DOUBLE AS rows_all, d, f1, f1_hat, (SELECT sum(own::INTEGER)::BIGINT FROM state) AS owned, (SELECT sum(m1 + m2)::BIGINT FROM state) AS ranks, round(abs(f1_hat - f1) / nullif(f1, 0), 4) AS err FROM counts, f"
    return f"SELECT * FROM ({with_(*parts, select=select)})"


register("singletons_at_scale", _at_scale, " UNION ALL ".join(_at_scale_sql(n, kind, x, rows) for n, kind, x in DATA for rows in SCALES))

# Communication --------------------------------------------------------------------------------------


def _communication_generated(s: SparkSession, d: str) -> DataFrame:
    """(data, b, dictionary, dense, sent): bytes of dictionaries and of dense sketches, and the register rows that tasks really send.

    The first grow with the sample, the second with sites and b only; the last, for one task with all sites, are two a register at most."""
    out = None
    for name, kind, x in DATA:
        sample, _ = generated(s, d, kind, x, k=64)
        sites = P.local_counts(sample).agg((F.count("*") * A.ENTRY_BYTES).alias("dictionary"), F.countDistinct("site").alias("sites"))
        # Each task has sites of its own; of the rows that it sends for a register, one task with all sites would send two at most.
        rows = Y.site_summary(sample, (10, 12, 14), ("d", "f1"), hashing=CHECKED).where("b > 0")
        sent = rows.groupBy("b", "slot").agg(F.least(F.count("*"), F.lit(2)).alias("n")).groupBy("b").agg(F.sum("n").alias("sent"))
        row = sent.crossJoin(F.broadcast(sites)).select(F.lit(name).alias("data"), "b", "dictionary", (c("sites") * F.call_function("shiftleft", F.lit(2).cast("long"), c("b"))).alias("dense"), "sent")
        out = row if out is None else out.unionByName(row)
    return out


def _communication_sql(name: str, kind: str, x: float, b: int) -> str:
    parts = [*generated_sql(kind, x, k=64), Q.LOCAL, Q.registers(b)]
    sent = "(SELECT sum(least(2, n))::BIGINT FROM (SELECT count(*) AS n FROM regs GROUP BY reg))"
    return "SELECT * FROM (" + with_(*parts, select=f"SELECT '{name}' AS data, {b} AS b, count(*) * {A.ENTRY_BYTES} AS dictionary, count(DISTINCT site) * {2 << b} AS dense, {sent} AS sent FROM local") + ")"


register("communication_generated", _communication_generated, " UNION ALL ".join(_communication_sql(n, kind, x, b) for n, kind, x in DATA for b in (10, 12, 14)))

# Routes ---------------------------------------------------------------------------------------------


def _routes(s: SparkSession, d: str, k: int = MACHINES, b: int = 10) -> DataFrame:
    """All register routes on one layout of many sites."""
    r = regs(s, d, k=k, b=b)
    out = None
    for name, one in {"runner_up": G.singletons_runner_up(r, b), "tree": G.singletons_tree(r, b, k), "prefix_suffix": G.singletons_prefix_suffix(r, b), "direct": G.singletons_direct(r, b)}.items():
        row = rounded(one).select(F.lit(name).alias("route"), F.lit(M.merge_count(name, k)).cast("long").alias("merges"), "f1_hat")
        out = row if out is None else out.unionByName(row)
    return out


register(
    "routes_of_many_sites",
    _routes,
    with_(
        Q.sample(MAIN, RATE, MACHINES), Q.LOCAL, Q.registers(10), Q.f1_direct(10, "smooth"),
        select="SELECT route, merges, round(f1_hat, 3) AS f1_hat FROM f1, (VALUES " + ", ".join(f"('{r}', {M.merge_count(r, MACHINES)}::BIGINT)" for r in ("runner_up", "tree", "prefix_suffix", "direct")) + ") t(route, merges)",
    ),
)


def chosen_evidence(s: SparkSession, d: str, name: str, b: int = 10, q: float = RATE, k: int = 64) -> DataFrame:
    """Evidence by the route that the local dictionaries call for, and its name: the choice carried out.

    The driver reads one row of the plan: bytes of both routes and the local share of singletons."""
    sample = by_site(sampled(s, d, name, q, k))
    route = A.plan_route(P.local_counts(sample, "runlength"), b).first()["route"]
    if route == "dictionary":
        e = P.evidence_of_counts(P.dictionary(sample)).select("n", c("d").cast("double").alias("d"), c("f1").cast("double").alias("f1"))
    else:
        e = Y.sketched_evidence(sample, b, E.needs("gee"), hashing=CHECKED).select("n", "d", "f1")
    return e.withColumn("route", F.lit(route))


def _chosen(s: SparkSession, d: str, name: str) -> DataFrame:
    e = chosen_evidence(s, d, name).crossJoin(F.broadcast(population(s, d, name)))
    return e.select("route", F.round(E.gee(c("d"), c("f1"), c("rows_all"), c("n")), 2).alias("gee"))


for _w in (MAIN, "event_type"):
    _few = f"(SELECT count(*) * {A.ENTRY_BYTES} <= count(DISTINCT site) * {2 << 10} OR count(*) FILTER (c = 1) < 0.02 * count(*) FROM local)"
    _gee = "{d} + (sqrt(sk.rows_all / sk.n::DOUBLE) - 1) * {f1}"
    register(
        f"gee_by_chosen_route_{_w}",
        lambda s, d, w=_w: _chosen(s, d, w),
        with_(
            *Q.sketched(_w, RATE, 64, 10), Q.PROFILE, Q.EVIDENCE,
            select=f"SELECT CASE WHEN {_few} THEN 'dictionary' ELSE 'sketch' END AS route, round(CASE WHEN {_few} THEN {_gee.format(d='ev.d', f1='ev.f1')} ELSE {_gee.format(d='sk.d', f1='sk.f1')} END, 2) AS gee FROM ev, sk",
        ),
    )
register("gee_sketched_classes", lambda s, d: rounded(sketched(s, d, "event_type", 10, needs=("d", "f1"), whole_sites=True).select("n", "d", "f1", "rows_all")), with_(*Q.sketched("event_type", RATE, 64, 10), select="SELECT n, round(d, 3) AS d, round(f1, 3) AS f1, rows_all FROM sk"))
