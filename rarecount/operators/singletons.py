"""Values seen once overall, from two sketches of each site.

A value is a singleton of the union if it is one of a site and no other site has it. With Y_j the union
of all sites but j and S_j the singletons of j, their number is the sum over j of |S_j u Y_j| - |Y_j|. Every
route below computes these terms; they differ in how the unions Y_j come about.

Input of the register routes is (site, reg, rd, r1): the best rank of all values and of local singletons.
S_j never exceeds site j's own register, so only the owner of a register's maximum has a term there:
elsewhere the others' union is the whole union. The terms of a route are thus sums over owned registers.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions.hashing import register_and_rank
from ..functions.sketches import ESTIMATES


def site_registers(local: DataFrame, b: int, seed: int = 0, hashing: str = "fast", count: str = "c") -> DataFrame:
    """(site, reg, rd, r1) of local dictionaries; partial aggregation leaves at most 2^b rows a site."""
    reg, r = register_and_rank(F.col("v"), b, seed, hashing)
    d = local.where(F.col(count) > 0).select("site", reg.alias("reg"), r.alias("r"), F.col(count).alias("c"))
    return d.groupBy("site", "reg").agg(F.max("r").alias("rd"), F.coalesce(F.max(F.when(F.col("c") == 1, F.col("r"))), F.lit(0)).cast("int").alias("r1"))


def register_state(registers: DataFrame) -> DataFrame:
    """(reg, m1, owner, s_owner, m2): best rank, who has it, the owner's singleton rank, the best other rank.

    2^b rows for any number of sites. Only the first two of each register survive the map side.
    """
    w = Window.partitionBy("reg").orderBy(F.desc("rd"), "site")
    two = registers.withColumn("pos", F.row_number().over(w)).where("pos <= 2")
    first = lambda c: F.max(F.when(F.col("pos") == 1, F.col(c)))
    return two.groupBy("reg").agg(
        first("rd").alias("m1"), first("site").alias("owner"), first("r1").alias("s_owner"), F.coalesce(F.max(F.when(F.col("pos") == 2, F.col("rd"))), F.lit(0)).alias("m2")
    )


def _p(rank: Column) -> Column:
    return F.pow(F.lit(2.0), -rank)


def leave_one_out(owned: DataFrame, b: int) -> DataFrame:
    """(site, z_y, e_y, z_ys, e_ys) from (reg, m1, owner, s_owner, m2): harmonic sums and empty registers
    of Y_j and of Y_j u S_j, by subtraction from those of the whole union. Sites that own nothing have no row: their term is 0."""
    m = 1 << b
    best = F.greatest("m2", "s_owner")
    total = owned.agg((F.coalesce(F.sum(_p(F.col("m1"))), F.lit(0.0)) + (m - F.count("*"))).alias("z"), (m - F.count("*")).alias("e"))
    own = owned.groupBy(F.col("owner").alias("site")).agg(
        F.sum(_p(F.col("m2")) - _p(F.col("m1"))).alias("dy"),
        F.sum((F.col("m2") == 0).cast("long")).alias("ey"),
        F.sum(_p(best) - _p(F.col("m1"))).alias("dys"),
        F.sum((best == 0).cast("long")).alias("eys"),
    )
    d = own.crossJoin(F.broadcast(total))
    return d.select("site", (F.col("z") + F.col("dy")).alias("z_y"), (F.col("e") + F.col("ey")).alias("e_y"), (F.col("z") + F.col("dys")).alias("z_ys"), (F.col("e") + F.col("eys")).alias("e_ys"))


def site_terms(loo: DataFrame, b: int, estimator: str = "smooth") -> DataFrame:
    est = ESTIMATES[estimator]
    d = loo.select("site", est(F.col("z_y"), F.col("e_y"), b).alias("y_est"), est(F.col("z_ys"), F.col("e_ys"), b).alias("ys_est"))
    return d.withColumn("uniq_est", F.col("ys_est") - F.col("y_est"))


def total_terms(terms: DataFrame) -> DataFrame:
    return terms.agg(F.coalesce(F.sum("uniq_est"), F.lit(0.0)).alias("f1_hat"))


def clamped(f1: Column, d: Column) -> Column:
    """Noise can leave [0, d]."""
    return F.greatest(F.lit(0.0), F.least(f1, d))


# Routes from registers ------------------------------------------------------------------------------


def singletons_runner_up(registers: DataFrame, b: int, estimator: str = "smooth") -> DataFrame:
    """One row f1_hat, without any merge of sketches: the flagship."""
    return total_terms(site_terms(leave_one_out(register_state(registers), b), b, estimator))


def _owned(registers: DataFrame, others: DataFrame) -> DataFrame:
    """Registers with the best rank of the others, kept where the site itself is above it."""
    d = registers.join(others, ["site", "reg"], "left").select("reg", F.col("rd").alias("m1"), F.col("site").alias("owner"), F.col("r1").alias("s_owner"), F.coalesce("y", F.lit(0)).alias("m2"))
    top = Window.partitionBy("reg").orderBy(F.desc("m1"), "owner")
    return d.withColumn("pos", F.row_number().over(top)).where("pos = 1").drop("pos")


def others_direct(registers: DataFrame) -> DataFrame:
    """Y_j by merging all other sites anew for each site: the quadratic baseline."""
    a, o = registers.select("site", "reg"), registers.select(F.col("site").alias("o"), "reg", "rd")
    return a.join(o, "reg").where("o <> site").groupBy("site", "reg").agg(F.max("rd").alias("y"))


def singletons_direct(registers: DataFrame, b: int, estimator: str = "smooth") -> DataFrame:
    return total_terms(site_terms(leave_one_out(_owned(registers, others_direct(registers)), b), b, estimator))


def others_tree(registers: DataFrame, k: int) -> DataFrame:
    """Y_j from shared partial unions: node n of a level is the union of nodes 2n and 2n + 1 below, and Y_j
    is the union of the siblings on the way from leaf j to the root. A missing sibling has no rows.

    All levels are made in one aggregation: a register is of one node a level, and partial aggregation
    unites what falls together before anything is sent."""
    top = max(0, (k - 1).bit_length() - 1)
    ways = registers.select("site", "reg", "rd", F.explode(F.sequence(F.lit(0), F.lit(top))).alias("level"))
    nodes = ways.groupBy("reg", "level", F.expr("shiftright(cast(site as int), level)").alias("node")).agg(F.max("rd").alias("rd"))
    ways = ways.select("site", "reg", "level", F.expr("shiftright(cast(site as int), level) ^ 1").alias("node"))
    return ways.join(nodes, ["reg", "level", "node"]).groupBy("site", "reg").agg(F.max("rd").alias("y"))


def singletons_tree(registers: DataFrame, b: int, k: int, estimator: str = "smooth") -> DataFrame:
    return total_terms(site_terms(leave_one_out(_owned(registers, others_tree(registers, k)), b), b, estimator))


def others_prefix_suffix(registers: DataFrame) -> DataFrame:
    """Y_j as the union of all sites before and all after j, register by register."""
    w = Window.partitionBy("reg").orderBy("site")
    before = F.max("rd").over(w.rowsBetween(Window.unboundedPreceding, -1))
    after = F.max("rd").over(w.rowsBetween(1, Window.unboundedFollowing))
    return registers.select("site", "reg", F.greatest(F.coalesce(before, F.lit(0)), F.coalesce(after, F.lit(0))).alias("y"))


def singletons_prefix_suffix(registers: DataFrame, b: int, estimator: str = "smooth") -> DataFrame:
    return total_terms(site_terms(leave_one_out(_owned(registers, others_prefix_suffix(registers)), b), b, estimator))


def singletons_two_site(registers: DataFrame, b: int, estimator: str = "smooth") -> DataFrame:
    """Two sites, by the two differences directly; sites 0 and 1."""
    est = ESTIMATES[estimator]
    m = 1 << b
    side = lambda s, c: F.max(F.when(F.col("site") == s, F.col(c)).otherwise(0))
    wide = registers.groupBy("reg").agg(side(0, "rd").alias("x"), side(1, "rd").alias("y"), side(0, "r1").alias("sx"), side(1, "r1").alias("sy"))

    def card(c: Column) -> Column:
        full = F.count(F.when(c > 0, 1))
        return est(F.coalesce(F.sum(F.when(c > 0, _p(c))), F.lit(0.0)) + (m - full), m - full, b)

    x, y, sx, sy = (F.col(c) for c in ("x", "y", "sx", "sy"))
    return wide.agg((card(F.greatest(sx, y)) - card(y) + card(F.greatest(sy, x)) - card(x)).alias("f1_hat"))


def singletons_median(local: DataFrame, b: int, replicas: int = 3, estimator: str = "smooth", hashing: str = "fast") -> DataFrame:
    """The median over independent hash seeds."""
    parts = None
    for seed in range(replicas):
        one = singletons_runner_up(site_registers(local, b, seed, hashing), b, estimator)
        parts = one if parts is None else parts.unionByName(one)
    return parts.agg(F.percentile("f1_hat", 0.5).alias("f1_hat"))


# Routes from native sketches ------------------------------------------------------------------------


def site_summaries(local: DataFrame, b: int, kind: str = "hll") -> DataFrame:
    """(site, n, d, a, s): two binary sketches of each site, made on the map side."""
    h = F.xxhash64("v")
    once = F.when(F.col("c") == 1, h)
    agg = (lambda x: F.hll_sketch_agg(x, F.lit(b))) if kind == "hll" else (lambda x: F.theta_sketch_agg(x, F.lit(b)))
    return local.groupBy("site").agg(F.sum("c").alias("n"), F.count("*").alias("d"), agg(h).alias("a"), agg(once).alias("s"))


def hll_terms(summaries: DataFrame, y: DataFrame) -> DataFrame:
    """Estimates of native sketches depend on how they were put together. The union with itself has an estimate of its registers alone,
    so that equal unions count alike whatever the route."""
    plain = lambda x: F.hll_sketch_estimate(F.hll_union(x, x))
    d = summaries.join(y, "site", "left").select("site", "y", "s", F.hll_union("y", "s").alias("ys"))
    y_est = F.when(F.col("y").isNull(), 0).otherwise(plain("y"))
    both = F.when(F.col("y").isNull(), F.hll_sketch_estimate("s")).otherwise(plain("ys"))
    return d.select("site", y_est.cast("double").alias("y_est"), both.cast("double").alias("ys_est")).withColumn("uniq_est", F.col("ys_est") - F.col("y_est"))


def hll_others_direct(summaries: DataFrame) -> DataFrame:
    a, o = summaries.select("site"), summaries.select(F.col("site").alias("o"), "a")
    return a.crossJoin(o).where("o <> site").groupBy("site").agg(F.hll_union_agg("a").alias("y"))


def premerge_tree(summaries: DataFrame, k: int) -> DataFrame:
    """(level, node, a): all shared partial unions, about 2k sketches."""
    level, nodes = 0, summaries.select(F.col("site").cast("int").alias("node"), "a")
    out = nodes.withColumn("level", F.lit(0))
    while (1 << level) < k:
        level += 1
        nodes = nodes.groupBy(F.shiftright("node", 1).alias("node")).agg(F.hll_union_agg("a").alias("a"))
        out = out.unionByName(nodes.withColumn("level", F.lit(level)))
    return out


def hll_others_tree(summaries: DataFrame, k: int) -> DataFrame:
    top = max(0, (k - 1).bit_length() - 1)
    ways = summaries.select("site", F.explode(F.sequence(F.lit(0), F.lit(top))).alias("level"))
    ways = ways.withColumn("node", F.expr("shiftright(site, level) ^ 1"))
    return ways.join(premerge_tree(summaries, k), ["level", "node"]).groupBy("site").agg(F.hll_union_agg("a").alias("y"))


def others_by_position(summaries: DataFrame, united, join) -> DataFrame:
    """Running unions both ways. One task holds the sites' sketches in turn, so it is for some thousands of sites.
    Edges are made null by their position: the union of an empty frame has a default size that can't be joined."""
    up, down = Window.orderBy("site"), Window.orderBy(F.desc("site"))
    frame = lambda w: w.rowsBetween(Window.unboundedPreceding, -1)
    d = summaries.select(
        "site",
        F.when(F.row_number().over(up) > 1, united("a").over(frame(up))).alias("p"),
        F.when(F.row_number().over(down) > 1, united("a").over(frame(down))).alias("q"),
    )
    both = F.when(F.col("p").isNotNull() & F.col("q").isNotNull(), join("p", "q"))
    return d.select("site", F.coalesce(both, "p", "q").alias("y")).where("y is not null")


def hll_others_prefix_suffix(summaries: DataFrame) -> DataFrame:
    return others_by_position(summaries, F.hll_union_agg, F.hll_union)


def singletons_hll(summaries: DataFrame, route: str, k: int) -> DataFrame:
    y = {"direct": hll_others_direct, "tree": lambda s: hll_others_tree(s, k), "prefix_suffix": hll_others_prefix_suffix}[route](summaries)
    return total_terms(hll_terms(summaries, y))


def singletons_theta(summaries: DataFrame) -> DataFrame:
    """The sum of |S_j without Y_j|, directly: these sketches have a difference. 3 k unions."""
    y = others_by_position(summaries, F.theta_union_agg, F.theta_union)
    d = summaries.select("site", "s").join(y, "site", "left")
    one = F.when(F.col("y").isNull(), F.theta_sketch_estimate("s")).otherwise(F.theta_sketch_estimate(F.theta_difference("s", "y")))
    return d.agg(F.coalesce(F.sum(one), F.lit(0)).cast("double").alias("f1_hat"))


# Exact counterparts ---------------------------------------------------------------------------------


def singletons_exact_sets(local: DataFrame) -> DataFrame:
    """The same formula with sets: local singletons that no other site has. One row f1."""
    holders = local.groupBy("v").agg(F.count("*").alias("sites"), F.max("c").alias("most"))
    return holders.agg(F.coalesce(F.sum(((F.col("sites") == 1) & (F.col("most") == 1)).cast("long")), F.lit(0)).alias("f1"))


def exact_terms(local: DataFrame) -> DataFrame:
    """(site, uniq): each site's exact term."""
    w = Window.partitionBy("v")
    d = local.withColumn("sites", F.count("*").over(w))
    return d.groupBy("site").agg(F.sum(((F.col("sites") == 1) & (F.col("c") == 1)).cast("long")).alias("uniq"))


def singletons_two_site_exact(x: DataFrame, y: DataFrame) -> DataFrame:
    """Values single in one dictionary and absent from the other, by anti joins both ways."""
    a = x.where("c = 1").select("v").join(y.select("v"), "v", "left_anti")
    return a.unionByName(y.where("c = 1").select("v").join(x.select("v"), "v", "left_anti"))


def intersection_estimate(x: DataFrame, y: DataFrame, b: int) -> DataFrame:
    """|X n Y| by inclusion and exclusion of sketches, whose error is that of the union."""
    sk = lambda d, n: d.agg(F.hll_sketch_agg(F.xxhash64("v"), F.lit(b)).alias(n))
    d = sk(x, "a").crossJoin(sk(y, "b"))
    est = F.hll_sketch_estimate
    return d.select((est("a") + est("b") - est(F.hll_union("a", "b"))).alias("common_hat"))


def intersection_registers(registers: DataFrame, b: int, estimator: str = "smooth") -> DataFrame:
    """The same of sites 0 and 1 from registers."""
    est, m = ESTIMATES[estimator], 1 << b
    side = lambda s: F.coalesce(F.max(F.when(F.col("site") == s, F.col("rd"))), F.lit(0))
    wide = registers.groupBy("reg").agg(side(0).alias("x"), side(1).alias("y"))

    def card(r: Column) -> Column:
        full = F.count(F.when(r > 0, 1))
        return est(F.coalesce(F.sum(F.when(r > 0, _p(r))), F.lit(0.0)) + (m - full), m - full, b)

    return wide.agg((card(F.col("x")) + card(F.col("y")) - card(F.greatest("x", "y"))).alias("common_hat"))


def intersection_from_singletons(dx: Column, dy: Column, f1: Column) -> Column:
    """For two sets, f1 of their sum is |X| + |Y| - 2 |X n Y|: exact f1 would give exact intersections."""
    return (dx + dy - f1) / 2
