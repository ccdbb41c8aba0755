"""Queries of the operators around the methods: joins, rollups, windows, sets, nested values, SQL surface, streams."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions import estimators as E
from ..functions import sketches as K
from ..functions import sqlapi
from ..operators import analysis as A
from ..operators import metrics as M
from ..operators import profile as P
from ..operators import singletons as G
from ..sources import sinks
from ..sources.tables import LINE, table
from ..streaming import windows as W
from . import sqltext as Q
from .queries import CHECKED, MAIN, RATE, SITES, _near, c, evidence, local, near_sql, oracle_sql, queries, register, sampled, sql_evidence, values, with_

# Sources and sinks ----------------------------------------------------------------------------------

register(
    "scan_parquet",
    lambda s, d: table(s, d, "lineitem").where("l_quantity between 10 and 20").groupBy("l_returnflag").agg(F.count("*").alias("n")),
    "SELECT l_returnflag, count(*) AS n FROM lineitem WHERE l_quantity BETWEEN 10 AND 20 GROUP BY 1",
)


def _shared(spark: SparkSession) -> str:
    """A new folder in the place that driver and executors share."""
    return f"{sinks.shared_root(spark)}/rarecount-{uuid.uuid4().hex}"


def _roundtrip(s: SparkSession, d: str) -> DataFrame:
    """Two batches of stored registers, read back together: the same state as from one pass."""
    path, both = _shared(s), local(s, d)
    for half in (0, 1):
        part = both.where(c("site") % 2 == half)
        sinks.write_registers(G.site_registers(part, 10, hashing=CHECKED), path, MAIN, f"b{half}")
    state = G.register_state(sinks.read_registers(s, path, MAIN))
    return state.select("reg", "m1", "m2")


register("sink_sketch_roundtrip", _roundtrip, with_(Q.sample(MAIN, RATE, SITES), Q.LOCAL, Q.registers(10), Q.STATE, select="SELECT reg, m1, m2 FROM state"))

# Projection, filters and joins ----------------------------------------------------------------------

register("value_key", lambda s, d: table(s, d, "lineitem").select(F.xxhash64("l_partkey", "l_suppkey").alias("k")).agg(F.countDistinct("k").alias("d")), "SELECT count(*) AS d FROM (SELECT DISTINCT l_partkey, l_suppkey FROM lineitem)")
register("null_values", lambda s, d: _nulls(s, d), with_("s AS (SELECT CASE WHEN o_custkey % 10 = 0 THEN NULL ELSE o_custkey END AS v FROM orders)", select="SELECT count(v) AS n, count(DISTINCT v) AS d, count(*) - count(v) AS nulls FROM s"))


def _nulls(s: SparkSession, d: str) -> DataFrame:
    v = table(s, d, "orders").select(F.when(c("o_custkey") % 10 != 0, c("o_custkey")).alias("v"))
    prof = P.exact_profile(v)
    ev = P.exact_evidence(prof).select("n", "d")
    return ev.crossJoin(v.agg(F.count(F.when(c("v").isNull(), 1)).alias("nulls")))


register("filter_singletons", lambda s, d: P.merged(local(s, d, "partkey")).where("c = 1 and v between 1 and 500").select("v"), with_(Q.sample("partkey", RATE, SITES), select="SELECT v FROM s WHERE v BETWEEN 1 AND 500 GROUP BY v HAVING count(*) = 1"))


def _broadcast_rate(s: SparkSession, d: str) -> DataFrame:
    """A small table of sites and rates thins a sample: 3 rows, a fixed size."""
    rates = s.createDataFrame([(0, 0.2), (1, 0.5), (2, 1.0)], "site int, rate double")
    j = sampled(s, d, k=3).join(F.broadcast(rates), "site")
    return j.groupBy("site", "rate").agg(F.count("*").alias("n"))


register("join_broadcast_rate", _broadcast_rate, with_(Q.sample(MAIN, RATE, 3), select="SELECT site, CASE site WHEN 0 THEN 0.2 WHEN 1 THEN 0.5 ELSE 1.0 END::DOUBLE AS rate, count(*) AS n FROM s GROUP BY 1, 2"))
register(
    "join_line_totalprice",
    lambda s, d: values(s, d, "totalprice").agg(F.count("*").alias("n"), F.countDistinct("v").alias("d")),
    with_(Q.everything("totalprice"), select="SELECT count(*) AS n, count(DISTINCT v) AS d FROM s"),
)
register(
    "join_semi",
    lambda s, d: values(s, d, "custkey").distinct().join(sampled(s, d, "custkey").select("v"), "v", "left_semi"),
    with_(Q.sample("custkey", RATE, SITES), select="SELECT DISTINCT v FROM s"),
)
register(
    "join_anti",
    lambda s, d: values(s, d, "custkey").distinct().join(sampled(s, d, "custkey").select("v"), "v", "left_anti"),
    with_(Q.sample("custkey", RATE, SITES), select="SELECT DISTINCT o_custkey AS v FROM orders WHERE o_custkey NOT IN (SELECT v FROM s)"),
)


def _bands(s: SparkSession, d: str) -> DataFrame:
    """A range join of the profile with bands of multiplicity."""
    bands = s.createDataFrame([("once", 1, 1), ("few", 2, 5), ("many", 6, 1 << 40)], "band string, lo long, hi long")
    j = P.exact_profile(values(s, d)).join(F.broadcast(bands), (c("i") >= c("lo")) & (c("i") <= c("hi")))
    return j.groupBy("band").agg(F.sum("f").alias("f"))


register("profile_bands", _bands, with_(Q.everything(MAIN), Q.PROFILE, select="SELECT CASE WHEN i = 1 THEN 'once' WHEN i <= 5 THEN 'few' ELSE 'many' END AS band, sum(f)::BIGINT AS f FROM prof GROUP BY 1"))


def _as_of(s: SparkSession, d: str) -> DataFrame:
    """For each event of one user group, the latest purchase before it: an as-of join by one window over both."""
    e = table(s, d, "events").select("event_id", "user_id", "ts", "event_type")
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    last = F.max(F.when(c("event_type") == "purchase", F.struct("ts", "event_id"))).over(w)
    return e.select("event_id", last.getField("event_id").alias("last_purchase"))


register(
    "sketch_as_of",
    _as_of,
    "SELECT event_id, max(CASE WHEN event_type = 'purchase' THEN struct_pack(ts := ts, e := event_id) END) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING).e AS last_purchase FROM events".replace("max(CASE", "(max(CASE").replace("1 PRECEDING).e", "1 PRECEDING)).e"),
)


def _interval(s: SparkSession, d: str) -> DataFrame:
    """Pairs of a user's purchase with events up to ten minutes after it: equal bins, then the interval itself."""
    e = table(s, d, "events").select("event_id", "user_id", F.unix_micros(c("ts").cast("timestamp")).alias("t"), "event_type")
    width = 600_000_000
    a = e.where("event_type = 'purchase'").select(c("event_id").alias("a"), "user_id", c("t").alias("ta"), F.explode(F.array(F.floor(c("t") / width), F.floor(c("t") / width) + 1)).alias("bin"))
    b = e.select(c("event_id").alias("b"), "user_id", c("t").alias("tb"), F.floor(c("t") / width).alias("bin"))
    j = a.join(b, ["user_id", "bin"]).where("tb > ta and tb <= ta + 600000000")
    return j.groupBy("user_id").agg(F.count("*").alias("pairs"))


register("join_interval", _interval, "SELECT a.user_id, count(*) AS pairs FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 10 MINUTE WHERE a.event_type = 'purchase' GROUP BY 1")

# Aggregates over levels -----------------------------------------------------------------------------

_LEVEL = "l_returnflag, l_linestatus"
register("distinct_cube", lambda s, d: table(s, d, "lineitem").cube("l_returnflag", "l_linestatus").agg(F.countDistinct("l_suppkey").alias("d")), f"SELECT {_LEVEL}, count(DISTINCT l_suppkey) AS d FROM lineitem GROUP BY CUBE ({_LEVEL})")
register("distinct_rollup", lambda s, d: table(s, d, "lineitem").rollup("l_returnflag", "l_linestatus").agg(F.countDistinct("l_partkey").alias("d")), f"SELECT {_LEVEL}, count(DISTINCT l_partkey) AS d FROM lineitem GROUP BY ROLLUP ({_LEVEL})")


def _grouping(s: SparkSession, d: str) -> DataFrame:
    df = table(s, d, "lineitem")
    return df.groupingSets([[c("l_returnflag")], [c("l_linestatus")]], "l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.countDistinct("l_orderkey").alias("d"))


register("grouping_sets_profile", _grouping, "SELECT l_returnflag, l_linestatus, count(*) AS n, count(DISTINCT l_orderkey) AS d FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus))")


def _rollup_sketches(s: SparkSession, d: str) -> DataFrame:
    """Register sketches of the finest level, merged upwards: equal to sketches of each level from scratch."""
    reg, r = K.register_and_rank(c("l_partkey"), 10, hashing=CHECKED)
    fine = table(s, d, "lineitem").select("l_returnflag", "l_linestatus", reg.alias("reg"), r.alias("r")).groupBy("l_returnflag", "l_linestatus", "reg").agg(F.max("r").alias("r"))
    return K.merged_registers(fine, ["l_returnflag"])


register(
    "rollup_sketches",
    _rollup_sketches,
    f"SELECT l_returnflag, ({Q.bits('d', 0)} % 1024)::INTEGER AS reg, max({Q.rank(Q.bits('d', 1))}) AS r FROM (SELECT l_returnflag, {Q.digest('0', 'l_partkey')} AS d FROM lineitem) GROUP BY 1, 2",
)


def _per_site(s: SparkSession, d: str) -> DataFrame:
    """Each site's estimates from native sketches stay near its exact counts."""
    summ = G.site_summaries(local(s, d, k=8), 12)
    return _near(summ.agg(F.sum(F.hll_sketch_estimate("a")).alias("x"), F.sum("d").alias("y")), c("x"), c("y"), 0.05)


register("sketch_per_site", _per_site, near_sql("SELECT count(*) FROM local", Q.sample(MAIN, RATE, 8), Q.LOCAL))

# Windows --------------------------------------------------------------------------------------------


def _ranks(s: SparkSession, d: str) -> DataFrame:
    """Event types by frequency: a handful of groups, so one window over all of them is of a bounded size."""
    counts = values(s, d, "event_type").groupBy("v").agg(F.count("*").alias("n"))
    w = Window.orderBy(F.desc("n"), "v")
    return counts.select("v", "n", F.row_number().over(w).alias("rn"), F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dr"), F.ntile(3).over(w).alias("tile"), F.round(F.percent_rank().over(w), 6).alias("pr"))


register(
    "rank_frequency",
    _ranks,
    "SELECT v, n, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, ntile(3) OVER w AS tile, round(percent_rank() OVER w, 6) AS pr FROM (SELECT event_type AS v, count(*) AS n FROM events GROUP BY 1) WINDOW w AS (ORDER BY n DESC, v)",
)


def _running(s: SparkSession, d: str) -> DataFrame:
    """Distinct users up to each day: first days per user, then a running sum over days."""
    first = table(s, d, "events").groupBy("user_id").agg(F.min(F.to_date("ts")).alias("day"))
    per_day = first.groupBy("day").agg(F.count("*").alias("fresh"))
    w = Window.orderBy("day").rowsBetween(Window.unboundedPreceding, 0)
    return per_day.select("day", "fresh", F.sum("fresh").over(w).alias("d"))


register("running_distinct", _running, "SELECT day, fresh, (sum(fresh) OVER (ORDER BY day))::BIGINT AS d FROM (SELECT day, count(*) AS fresh FROM (SELECT user_id, min(ts::DATE) AS day FROM events GROUP BY 1) GROUP BY 1)")


def _gaps(s: SparkSession, d: str) -> DataFrame:
    """Neighbouring multiplicities of a profile: how f changes from one i to the next. As many rows as multiplicities."""
    w = Window.orderBy("i")
    return P.exact_profile(values(s, d)).select("i", "f", (c("f") - F.lag("f").over(w)).alias("change"), F.lead("i").over(w).alias("next"))


register("profile_differences", _gaps, with_(Q.everything(MAIN), Q.PROFILE, select="SELECT i, f, f - lag(f) OVER (ORDER BY i) AS change, lead(i) OVER (ORDER BY i) AS next FROM prof"))
register("top_values", lambda s, d: values(s, d, "words").groupBy("v").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "v").limit(20), with_(Q.everything("words"), select="SELECT v, count(*) AS n FROM s GROUP BY v ORDER BY n DESC, v LIMIT 20"))

# Sets, strings, dates and nested values -------------------------------------------------------------


def _site_sets(s: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    loc = local(s, d, "partkey", k=2)
    return loc.where("site = 0").select("v"), loc.where("site = 1").select("v")


_SETS = [Q.sample("partkey", RATE, 2), "a AS (SELECT DISTINCT v FROM s WHERE site = 0)", "b AS (SELECT DISTINCT v FROM s WHERE site = 1)"]
register("set_union", lambda s, d: (lambda x: x[0].unionByName(x[1]).distinct())(_site_sets(s, d)), with_(*_SETS, select="SELECT v FROM a UNION SELECT v FROM b"))
register("set_union_all", lambda s, d: (lambda x: x[0].unionByName(x[1]))(_site_sets(s, d)), with_(*_SETS, select="SELECT v FROM a UNION ALL SELECT v FROM b"))
register("set_intersect", lambda s, d: (lambda x: x[0].intersect(x[1]))(_site_sets(s, d)), with_(*_SETS, select="SELECT v FROM a INTERSECT SELECT v FROM b"))
register("set_except", lambda s, d: (lambda x: x[0].exceptAll(x[1]))(_site_sets(s, d)), with_(*_SETS, select="SELECT v FROM a EXCEPT ALL SELECT v FROM b"))
register("word_profile", lambda s, d: P.exact_evidence(P.exact_profile(values(s, d, "words"))), with_(Q.everything("words"), Q.PROFILE, Q.EVIDENCE, select="SELECT * FROM ev"))
register(
    "distinct_by_month",
    lambda s, d: table(s, d, "orders").groupBy(F.date_format("o_orderdate", "yyyy-MM").alias("month")).agg(F.countDistinct("o_custkey").alias("d")),
    "SELECT strftime(o_orderdate, '%Y-%m') AS month, count(DISTINCT o_custkey) AS d FROM orders GROUP BY 1",
)


def _map(s: SparkSession, d: str) -> DataFrame:
    """A profile as one small map, summed by a higher-order function; for profiles, not for dictionaries."""
    m = P.exact_profile(values(s, d)).agg(F.map_from_entries(F.sort_array(F.collect_list(F.struct("i", "f")))).alias("m"))
    total = F.aggregate(F.map_entries("m"), F.lit(0).cast("long"), lambda a, e: a + e["key"] * e["value"])
    return m.select(F.size("m").alias("multiplicities"), total.alias("n"), F.element_at("m", F.lit(1).cast("long")).alias("f1"))


register("profile_as_map", _map, with_(Q.everything(MAIN), Q.PROFILE, select="SELECT count(*)::INTEGER AS multiplicities, sum(i * f)::BIGINT AS n, max(f) FILTER (i = 1) AS f1 FROM prof"))
register("json_distinct", lambda s, d: table(s, d, "events").agg(F.countDistinct(F.get_json_object("props", "$.k")).alias("d")), "SELECT count(DISTINCT json_extract_string(props, '$.k')) AS d FROM events")
register("array_distinct", lambda s, d: table(s, d, "embeddings").agg(F.countDistinct(F.xxhash64("embedding")).alias("d")), "SELECT count(DISTINCT embedding) AS d FROM embeddings")
register(
    "pivot_profile",
    lambda s, d: table(s, d, "lineitem").groupBy("l_linestatus").pivot("l_returnflag", ["A", "N", "R"]).agg(F.countDistinct("l_suppkey")),
    "SELECT l_linestatus, " + ", ".join(f"nullif(count(DISTINCT l_suppkey) FILTER (l_returnflag = '{x}'), 0) AS \"{x}\"" for x in "ANR") + " FROM lineitem GROUP BY 1",
)
register(
    "unpivot_evidence",
    lambda s, d: evidence(s, d).select("n", "d", "f1", "f2", "m2").unpivot([], ["n", "d", "f1", "f2", "m2"], "what", "amount"),
    with_(*sql_evidence()[:4], select="SELECT 'n' AS what, n AS amount FROM ev UNION ALL SELECT 'd', d FROM ev UNION ALL SELECT 'f1', f1 FROM ev UNION ALL SELECT 'f2', f2 FROM ev UNION ALL SELECT 'm2', m2 FROM ev"),
)


def _many_columns(s: SparkSession, d: str) -> DataFrame:
    """Evidence of several columns in one scan: the columns are stacked, then counted together."""
    cols = ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber"]
    stacked = table(s, d, "lineitem").select(F.explode(F.array(*[F.struct(F.lit(x).alias("col"), c(x).cast("long").alias("v")) for x in cols])).alias("e")).select("e.*")
    counts = stacked.groupBy("col", "v").agg(F.count("*").alias("i"))
    return counts.groupBy("col").agg(F.sum("i").alias("n"), F.count("*").alias("d"), F.count(F.when(c("i") == 1, 1)).alias("f1"))


register(
    "evidence_many_columns",
    _many_columns,
    " UNION ALL ".join(f"SELECT '{x}' AS col, sum(i)::BIGINT AS n, count(*) AS d, count(*) FILTER (i = 1) AS f1 FROM (SELECT count(*) AS i FROM lineitem GROUP BY {x})" for x in ("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber")),
)

# SQL surface ----------------------------------------------------------------------------------------


def _sql(s: SparkSession, d: str) -> DataFrame:
    sqlapi.register(s)
    evidence(s, d).createOrReplaceTempView("rarecount_evidence")
    return s.sql("SELECT round(ndv_gee(d, f1, rows_all, n), 4) AS gee, round(ndv_chao(d, f1), 4) AS chao FROM rarecount_evidence")


register("sql_estimate", _sql, with_(*sql_evidence(), select="SELECT round(d + (sqrt(rows_all / n::DOUBLE) - 1) * f1, 4) AS gee, round(d + f1::DOUBLE * f1 / (2 * (d - f1)), 4) AS chao FROM ev, pop"))


def _udtf(s: SparkSession, d: str) -> DataFrame:
    """Estimates as a table function of one evidence row."""
    e = evidence(s, d)
    e.createOrReplaceTempView("rarecount_evidence_rows")
    s.udtf.register("ndv_estimates", sqlapi.estimates_udtf())
    return s.sql("SELECT t.estimator, round(t.d_hat, 4) AS d_hat FROM rarecount_evidence_rows e, LATERAL ndv_estimates(e.d, e.f1, e.rows_all, e.n) t")


register("udtf_estimates", _udtf, with_(*sql_evidence(), select="SELECT 'gee' AS estimator, round(d + (sqrt(rows_all / n::DOUBLE) - 1) * f1, 4) AS d_hat FROM ev, pop UNION ALL SELECT 'chao_adjusted', round(d + f1::DOUBLE * f1 / (2 * (d - f1)), 4) FROM ev"))
register(
    "udaf_f2",
    lambda s, d: local(s, d, "suppkey").groupBy("site").agg(sqlapi.second_moment("c").alias("m2")),
    with_(Q.sample("suppkey", RATE, SITES), Q.LOCAL, select="SELECT site, sum(c * c)::BIGINT AS m2 FROM local GROUP BY site"),
)


def _gee_groups(s: SparkSession, d: str) -> DataFrame:
    """GEE per return flag: the evidence grouped, one estimate a row."""
    from ..functions.hashing import keyed, md5_bits
    from ..operators.sampling import bound

    line = table(s, d, "lineitem")
    digest = F.md5(keyed("s", *[F.expr(x) for x in LINE]))
    counts = line.where(md5_bits(digest, 0) < bound(RATE)).groupBy("l_returnflag", "l_partkey").agg(F.count("*").alias("i"))
    ev = counts.groupBy("l_returnflag").agg(F.sum("i").alias("n"), F.count("*").alias("d"), F.count(F.when(c("i") == 1, 1)).alias("f1"))
    pop = line.groupBy("l_returnflag").agg(F.count("*").alias("rows_all"))
    return ev.join(pop, "l_returnflag").select("l_returnflag", F.round(E.gee(c("d"), c("f1"), c("rows_all"), c("n")), 4).alias("d_hat"))


register(
    "gee_of_groups",
    _gee_groups,
    f"WITH x AS (SELECT l_returnflag, count(*) AS i FROM lineitem WHERE {Q.bits(Q.digest('s', *LINE), 0)} < {Q.bound(RATE)} GROUP BY l_returnflag, l_partkey), "
    "e AS (SELECT l_returnflag, sum(i) AS n, count(*) AS d, count(*) FILTER (i = 1) AS f1 FROM x GROUP BY 1), p AS (SELECT l_returnflag, count(*) AS rows_all FROM lineitem GROUP BY 1) "
    "SELECT l_returnflag, round(d + (sqrt(rows_all / n::DOUBLE) - 1) * f1, 4) AS d_hat FROM e JOIN p USING (l_returnflag)",
)

def _bucketed(s: SparkSession, d: str) -> DataFrame:
    """Local dictionaries of a table bucketed by site: the aggregate itself needs no exchange."""
    name = f"rarecount_bucketed_{uuid.uuid4().hex}"
    sinks.write_bucketed(sampled(s, d, k=8), name, "site", 8)
    return P.local_counts(s.table(name)).groupBy("site").agg(F.count("*").alias("d"), F.sum("c").alias("n"))


register("scan_bucketed", _bucketed, with_(Q.sample(MAIN, RATE, 8), Q.LOCAL, select="SELECT site, count(*) AS d, sum(c)::BIGINT AS n FROM local GROUP BY site"))


def _formats(s: SparkSession, d: str) -> DataFrame:
    """The same rows through CSV, JSON and ORC, read with a given schema."""
    from ..sources.tables import read

    base, o = _shared(s), table(s, d, "orders").select("o_orderkey", "o_custkey")
    out = None
    for kind in ("csv", "json", "orc"):
        o.write.format(kind).save(f"{base}/{kind}")
        row = read(s, f"{base}/{kind}", kind, o.schema).agg(F.countDistinct("o_custkey").alias("d")).select(F.lit(kind).alias("kind"), "d")
        out = row if out is None else out.unionByName(row)
    return out


register("scan_formats", _formats, "SELECT kind, d FROM (SELECT unnest(['csv', 'json', 'orc']) AS kind), (SELECT count(DISTINCT o_custkey) AS d FROM orders)")
#: The plain names of the first variants.
for _alias, _name in {
    "exact_profile": "exact_profile_orderkey", "population_profile": "population_profile_orderkey", "singletons_direct_registers": "singletons_direct",
    "scan_hll_registers": "hll_registers", "plan_route": "plan_route_orderkey", "filter_sample": "sample_by_hash",
}.items():
    register(_alias, queries()[_name], oracle_sql()[_name])


def _gee_bound(s: SparkSession, d: str) -> DataFrame:
    e = evidence(s, d).crossJoin(values(s, d).agg(F.countDistinct("v").alias("truth")))
    est = E.gee(c("d"), c("f1"), c("rows_all"), c("n"))
    limit = A.gee_error_bound(c("rows_all"), c("n"))
    return e.select(F.round(limit, 6).alias("bound"), (M.ratio_error(est, c("truth")) <= limit).alias("within"))


register("gee_error_bound", _gee_bound, with_(*sql_evidence(), select="SELECT round(sqrt(rows_all / n::DOUBLE), 6) AS bound, true AS within FROM ev, pop"))
SIZED, TARGETS = ("orderkey", "revenue", "custkey"), (0.02, 0.05, 0.1)


def _sketch_sizes(s: SparkSession, d: str) -> DataFrame:
    """(col, eps, c, b_fit, b_bound): log2 of the registers for a target error of f1 at the share of singletons that a column's sample has."""
    out = None
    for name in SIZED:
        share = A.assumption_ratio(P.evidence_of_counts(P.dictionary(sampled(s, d, name)))).select(F.round("ratio", 6).alias("c"))
        row = share.select(F.lit(name).alias("col"), F.explode(F.array(*map(F.lit, TARGETS))).alias("eps"), "c")
        out = row if out is None else out.unionByName(row)
    return out.select("*", A.b_for_share(c("eps"), c("c")).alias("b_fit"), A.b_for_share(c("eps"), c("c"), "bound").alias("b_bound"))


def _sketch_sizes_sql(name: str) -> str:
    size = lambda m: f"greatest(4, ceil(log2(pow({m}, 2))))::INTEGER"
    fit, bound = size(f"{1.04 * 2.3!r}::DOUBLE / (eps * sqrt(nullif(c, 0)))"), size("1.04::DOUBLE / (nullif(c, 0) * eps)")
    share = with_(*sql_evidence(name)[:4], select="SELECT round(f1 / d::DOUBLE, 6) AS c FROM ev")
    return f"SELECT '{name}' AS col, eps, c, {fit} AS b_fit, {bound} AS b_bound FROM ({share}), (SELECT unnest([{', '.join(map(str, TARGETS))}]::DOUBLE[]) AS eps)"


register("sketch_sizes", _sketch_sizes, " UNION ALL ".join(map(_sketch_sizes_sql, SIZED)))


def _share_agrees(s: SparkSession, d: str) -> DataFrame:
    """The expected share of singletons at the sample's rate beside the sample's own."""
    want = A.c_at(P.exact_profile(values(s, d)), [RATE])
    both = A.assumption_ratio(evidence(s, d)).crossJoin(want)
    return both.select(F.round("ratio", 6).alias("ratio"), "c", (F.abs(c("ratio") - c("c")) <= 0.1 * c("c")).alias("within"))


register(
    "expected_share_agrees",
    _share_agrees,
    f"SELECT round(a.ratio, 6) AS ratio, b.c, true AS within FROM ({oracle_sql()['assumption_ratio']}) a, ({oracle_sql()['share_by_rate']}) b WHERE b.q = {RATE!r}",
)


# Streams --------------------------------------------------------------------------------------------

register("stream_window_evidence", lambda s, d: W.replay(s, f"{d}/events.parquet", W.window_evidence, "1 hour"), W.WINDOW_SQL)
register("stream_session_counts", lambda s, d: W.replay(s, f"{d}/events.parquet", W.session_counts, "30 minutes"), W.SESSION_SQL)
register("stream_dedup", lambda s, d: W.replay(s, f"{d}/events.parquet", W.dedup, None), "SELECT count(DISTINCT event_id) AS n FROM events")
register("stream_window_distinct", lambda s, d: W.replay(s, f"{d}/events.parquet", W.window_sketches, "1 hour").select("start", "d", (F.abs(c("d_hat") - c("d")) <= 0.05 * c("d") + 1).alias("within")), W.DISTINCT_SQL)
register("stream_merged_windows", lambda s, d: W.merge_closed(W.replay(s, f"{d}/events.parquet", W.window_counts, "1 hour")), W.MERGED_SQL)
register("stream_sliding_evidence", lambda s, d: W.replay(s, f"{d}/events.parquet", W.sliding_evidence, "1 hour"), W.SLIDING_SQL)


def _site_sketches(s: SparkSession, d: str) -> DataFrame:
    """Counts of each closed window and site, and whether its two sketches agree with them."""
    x = W.replay(s, f"{d}/events.parquet", W.site_sketches, "1 hour")
    near = lambda sketch, n: F.abs(F.hll_sketch_estimate(sketch) - c(n)) <= 0.05 * c(n) + 1
    return x.select("start", "site", "n", "d", "f1", (near("a", "d") & near("s", "f1")).alias("within"))


def _sketch_merge(s: SparkSession, d: str) -> DataFrame:
    """Sketches of all closed windows and sites united, against the number of their users."""
    union = W.merged_sketches(s, f"{d}/events.parquet", "1 hour").agg(F.hll_sketch_estimate(F.hll_union_agg("a")).alias("x"))
    truth = W.replay(s, f"{d}/events.parquet", W.window_counts, "1 hour").agg(F.countDistinct("v").alias("t"))
    return _near(union.crossJoin(truth), c("x"), c("t"), 0.05)


register("stream_site_sketches", _site_sketches, W.SITE_SQL)
register("stream_sketch_merge", _sketch_merge, W.UNION_SQL)
register("stream_late_rows", lambda s, d: W.late_rows(s, W.thirds(s, f"{d}/events.parquet")), W.LATE_SQL)
