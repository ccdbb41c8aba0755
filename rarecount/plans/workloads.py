"""The experiments on a larger scale than the registered queries: errors by sketch size, sensitivity of singletons, communication, and time by route.

    python -m rarecount.plans.workloads errors|sensitivity|communication|routes|shuffle [folder of tables]

prints one JSON object a row. Data are the given tables' columns and generated populations, of which only the
profile and the sampled rows are ever made.
"""

from __future__ import annotations

import json
import sys
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import estimators as E
from ..operators import analysis as A
from ..operators import metrics as M
from ..operators import profile as P
from ..operators import sampling as S
from ..operators import singletons as G
from ..operators import summary as Y
from . import queries as Q

GENERATED = {f"poisson_{m}": ("poisson", m) for m in (50, 100, 200)} | {f"zipf_{x}": ("zipf", x) for x in (1.2, 1.5, 2.0)}


def population_profile(spark: SparkSession, name: str, scale: int) -> DataFrame:
    """(i, f) of a generated population of about ``scale`` values."""
    kind, x = GENERATED[name]
    return Q.poisson_profile(spark, x, scale) if kind == "poisson" else Q.zipf_profile(spark, x, scale, 20 * scale)


def simulated(profile: DataFrame, q: float, k: int, seed: int = 0) -> DataFrame:
    """(v, site, res): sampled rows of a population that is known by its profile only."""
    v = F.xxhash64("i", "c", "j")
    rows = S.sample_from_profile(profile, q, seed).select(v.alias("v"), F.explode(F.sequence(F.lit(1).cast("long"), F.col("c"))).alias("o"))
    h = F.xxhash64(F.lit(seed + 1), "v", "o")
    return rows.select("v", F.pmod(h, F.lit(k)).cast("int").alias("site"), (F.pmod(F.shiftrightunsigned(h, 24), F.lit(1 << 30)) < int(q * (1 << 30))).alias("res"))


def inputs(spark: SparkSession, sf: str, q: float, k: int, scale: int) -> Iterator[tuple[str, DataFrame, DataFrame, DataFrame]]:
    """(name, tagged sample, one row rows_all, one row truth) of every data set."""
    for name in ("orderkey", "totalprice", "revenue"):
        v = Q.values(spark, sf, name)
        yield name, Q.sampled(spark, sf, name, q, k), v.agg(F.count("*").alias("rows_all")), v.agg(F.countDistinct("v").alias("truth"))
    for name in GENERATED:
        prof = population_profile(spark, name, scale)
        total = prof.agg(P.moment(prof, 1).alias("rows_all"), P.moment(prof, 0).alias("truth"))
        yield name, simulated(prof, q, k), total.select("rows_all"), total.select("truth")


def errors(spark: SparkSession, sf: str, bits=(10, 12, 14, 16, 18), q: float = 0.1, k: int = 64, scale: int = 20_000) -> Iterator[dict]:
    """Relative errors of sketched estimates against exact-profile ones and against the truth."""
    for name, sample, rows_all, truth in inputs(spark, sf, q, k, scale):
        sk = Y.sketched_evidence(sample, list(bits)).crossJoin(rows_all)
        for r in Q.grid(spark, sk, P.evidence_of_counts(P.dictionary(sample)).crossJoin(rows_all), truth).collect():
            if r.vs_exact is not None:
                yield {"data": name} | r.asDict()


def sensitivity(spark: SparkSession, sf: str, b: int = 16, q: float = 0.1, k: int = 64, scale: int = 20_000) -> Iterator[dict]:
    """Relative error of the number of singletons by data."""
    for name, sample, _, _ in inputs(spark, sf, q, k, scale):
        exact = P.evidence_of_counts(P.dictionary(sample)).first()
        hat = Y.sketched_evidence(sample, b, ("d", "f1")).first().f1
        yield {"data": name, "b": b, "f1": exact.f1, "f1_hat": hat, "share": exact.f1 / exact.d if exact.d else None, "err": abs(hat - exact.f1) / exact.f1 if exact.f1 else None}


def communication(spark: SparkSession, sf: str, bits=(10, 12, 14), rates=(0.05, 0.1, 0.2, 0.4), k: int = 64) -> Iterator[dict]:
    """Bytes that leave the sites: dictionaries by rate, dense registers and native sketches as they are, by b."""
    for q in rates:
        local = Q.local(spark, sf, q=q, k=k).cache()
        native = {f"native_b{b}": M.total_bytes(M.sketch_bytes(G.site_summaries(local, b))).first().total for b in bits}
        yield {"q": q, "dictionary": local.count() * A.ENTRY_BYTES} | {f"sketch_b{b}": k * (2 << b) for b in bits} | native
        local.unpersist()


def routes(spark: SparkSession, sf: str, b: int = 10, sites=(4, 16, 64, 256, 1024, 4096), direct_up_to: int = 256) -> Iterator[dict]:
    """Seconds and unions of each route as the number of sites grows; the quadratic one only up to a number of them."""
    for k in sites:
        regs = G.site_registers(Q.local(spark, sf, k=k), b).cache()
        regs.count()
        for route, run in {
            "direct": lambda r=regs: G.singletons_direct(r, b),
            "tree": lambda r=regs, k=k: G.singletons_tree(r, b, k),
            "prefix_suffix": lambda r=regs: G.singletons_prefix_suffix(r, b),
            "runner_up": lambda r=regs: G.singletons_runner_up(r, b),
        }.items():
            if route == "direct" and k > direct_up_to:
                continue
            hat, s = M.timed(lambda f=run: f().first().f1_hat)
            yield {"k": k, "b": b, "route": route, "seconds": round(s, 3), "merges": M.merge_count(route, k), "f1_hat": hat}
        regs.unpersist()


def gee_both_ways(sample: DataFrame, rows_all: int, b: int) -> dict[str, DataFrame]:
    """The whole estimate by the dictionary merge and by sketches, from the same sample."""
    exact, sk = P.evidence_of_counts(P.dictionary(sample)), Y.sketched_evidence(sample, b, E.needs("gee"))
    return {n: e.select(E.gee(F.col("d"), F.col("f1"), F.lit(rows_all), F.col("n")).alias("gee")) for n, e in (("dictionary", exact), ("sketch", sk))}


def shuffle(spark: SparkSession, sf: str, rates=(0.1, 0.2, 0.4, 0.8), b: int = 10, name: str = "extendedprice") -> Iterator[dict]:
    """Bytes read and shuffled, and seconds, of GEE both ways."""
    rows_all = Q.values(spark, sf, name).count()
    for q in rates:
        for route, df in gee_both_ways(Q.sampled(spark, sf, name, q), rows_all, b).items():
            got: dict = {}

            def run(df=df, got=got):
                got["gee"], got["seconds"] = M.timed(lambda: df.first().gee)

            io = M.stage_io(spark, run)
            yield {"q": q, "route": route} | got | io


def main(args: list[str]) -> None:
    run = {"errors": errors, "sensitivity": sensitivity, "communication": communication, "routes": routes, "shuffle": shuffle}[args[0]]
    spark = SparkSession.builder.getOrCreate()
    for row in run(spark, args[1] if len(args) > 1 else "/root/testdata/sf0.01"):
        print(json.dumps(row), flush=True)


if __name__ == "__main__":
    main(sys.argv[1:])
