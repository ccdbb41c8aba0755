"""Evidence of a sample from sketches that are made where its rows are: one scan, no exchange of values.

Each task sorts its rows by (site, hash), counts the runs (its local dictionaries), and sends only what the
union of all sites can still need: per register the two best sites, counters of the second moment, and the number of rows. What
leaves a task is bounded by the sketches' size, whatever its rows and however many sites it holds.

Rows of a summary are (b, kind, slot, site, rd, r1, s): registers of the sample and of its resample, for each
sketch size b (rd: best rank of all values of the site, r1: of those it saw once), counters (slot is the bucket, s the
signed sum), and the number of rows (s); the last two have b = 0.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import two_words
from ..functions.sketches import ESTIMATES_SQL
from .profile import in_runs, runs

#: Kinds of summary rows; a counter row of the sketch's k-th line is COUNTERS + k.
SAMPLE, RESAMPLE, ROWS, COUNTERS = 0, 1, 2, 3
SCHEMA = "b int, kind int, slot int, site long, rd int, r1 int, s long"
#: What estimators need -> the kinds to make.
KINDS = {"d": SAMPLE, "f1": SAMPLE, "d_res": RESAMPLE, "f1_res": RESAMPLE, "m2": COUNTERS}


def kinds_for(needs: Iterable[str]) -> set[int]:
    return {KINDS[x] for x in needs if x in KINDS}


def ranks(low: np.ndarray) -> np.ndarray:
    """Position of the first one in 32 bits, from 1; 33 if there is none."""
    return (33 - np.frexp(low.astype(np.float64))[1]).astype(np.int32)


def best_two(site: np.ndarray, reg: np.ndarray, rd: np.ndarray, r1: np.ndarray, prune: bool = True) -> tuple[np.ndarray, ...]:
    """One row per (site, reg) with the best ranks; with ``prune``, only of each register's two best sites.

    A row that goes has two other sites ahead of it, whose ranks can only grow. If its site still comes to own the
    register, by another row, the runner-up is no less than what went, so no difference of unions changes.
    """
    order = np.lexsort((site, reg))
    site, reg, rd, r1 = site[order], reg[order], rd[order], r1[order]
    starts = np.flatnonzero(np.append(True, (site[1:] != site[:-1]) | (reg[1:] != reg[:-1]))) if len(reg) else np.zeros(0, np.int64)
    if len(starts):
        site, reg, rd, r1 = site[starts], reg[starts], np.maximum.reduceat(rd, starts), np.maximum.reduceat(r1, starts)
    if prune and len(reg):
        order = np.lexsort((site, -rd, reg))
        site, reg, rd, r1 = site[order], reg[order], rd[order], r1[order]
        third = np.zeros(len(reg), bool)
        third[2:] = reg[2:] == reg[:-2]
        site, reg, rd, r1 = site[~third], reg[~third], rd[~third], r1[~third]
    return site, reg, rd, r1


def buckets(g: np.ndarray, depth: int, width: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(bucket, sign) of each line of the counters: 64 / depth bits of the second word each, the lowest of them the sign."""
    bits = 64 // depth
    word = g.view(np.uint64)
    for k in range(depth):
        part = (word >> np.uint64(k * bits)) & np.uint64((1 << bits) - 1)
        yield ((part >> np.uint64(1)) % np.uint64(width)).astype(np.int64), 1 - 2 * (part & np.uint64(1)).astype(np.int64)


def site_summary(
    sample: DataFrame, b: int | Sequence[int], needs: Iterable[str] = ("d", "f1"), depth: int = 3, width: int = 20_000, seed: int = 0, hashing: str = "fast", prune: bool = True
) -> DataFrame:
    """Summary rows of a tagged sample (v, site, res). One scan and no exchange.

    ``prune=False`` keeps all registers of all sites, for routes and measures that need them.
    """
    kinds, sizes = kinds_for(needs), [b] if isinstance(b, int) else list(b)
    h, g = two_words(F.col("v"), seed, hashing)
    rows = in_runs(sample, h.alias("h"), g.alias("g"))
    names, types = ["b", "kind", "slot", "site", "rd", "r1", "s"], (pa.int32(), pa.int32(), pa.int32(), pa.int64(), pa.int32(), pa.int32(), pa.int64())

    def packed(bits: int, kind: int, slot: np.ndarray, site: np.ndarray, rd: np.ndarray, r1: np.ndarray, s: np.ndarray) -> pa.RecordBatch:
        cols = np.full(len(slot), bits), np.full(len(slot), kind), slot, site, rd, r1, s
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, types, strict=True)], names=names)

    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        none = np.zeros(0, np.int64)
        best = {(x, k): (none, none, none.astype(np.int32), none.astype(np.int32)) for x in sizes for k in (SAMPLE, RESAMPLE) if k in kinds}
        counters, n = np.zeros((depth, width), np.int64), 0
        for (site, hs, gs), c, c_res in runs(batches, 3):
            site, hs, gs = (x.to_numpy() for x in (site, hs, gs))
            n += int(c.sum())
            high, rank = hs >> np.int64(32), ranks(hs & np.int64(0xFFFFFFFF))
            for (x, k), held in best.items():
                have = c if k == SAMPLE else c_res
                some = have > 0
                new = site[some], (high & np.int64((1 << x) - 1))[some], rank[some], np.where(have[some] == 1, rank[some], 0).astype(np.int32)
                got = best_two(*(np.concatenate(y) for y in zip(held, new, strict=True)), prune)
                if not prune:
                    yield packed(x, k, got[1], got[0], got[2], got[3], np.zeros(len(got[0]), np.int64))
                    got = held
                best[x, k] = got
            if COUNTERS in kinds:
                for k, (at, sign) in enumerate(buckets(gs, depth, width)):
                    counters[k] += np.bincount(at, weights=sign * c, minlength=width).astype(np.int64)
        for (x, k), (site, reg, rd, r1) in best.items():
            if len(reg):
                yield packed(x, k, reg, site, rd, r1, np.zeros(len(reg), np.int64))
        for k in range(depth):
            at = np.flatnonzero(counters[k])
            if len(at):
                zero = np.zeros(len(at), np.int32)
                yield packed(0, COUNTERS + k, at, np.full(len(at), -1), zero, zero, counters[k][at])
        if n:
            one = np.zeros(1, np.int32)
            yield packed(0, ROWS, one, np.full(1, -1), one, one, np.array([n]))

    return rows.mapInArrow(make, SCHEMA)


def union_state(summary: DataFrame) -> DataFrame:
    """(b, kind, slot, m1, owner, s_owner, m2, s): all tasks' rows merged. One exchange, by slot."""
    key = ["b", "kind", "slot"]
    rows = summary.repartition(*key).groupBy(*key, "site").agg(F.expr("max(rd) as rd"), F.expr("max(r1) as r1"), F.expr("sum(s) as s"))
    two = rows.selectExpr("*", "row_number() over (partition by b, kind, slot order by rd desc, site) as pos").where("pos <= 2")
    first = [F.expr(f"max(if(pos = 1, {x}, null)) as {y}") for x, y in (("rd", "m1"), ("site", "owner"), ("r1", "s_owner"), ("s", "s"))]
    return two.groupBy(*key).agg(*first, F.expr("coalesce(max(if(pos = 2, rd, null)), 0) as m2"))


#: From one row a slot to one row a (b, kind): first the sums over the slots that a site owns, then each site's difference.
_OWNED = (
    "count(*) as cells", "sum(pow(2d, -m1)) as p", "sum(pow(2d, -m2) - pow(2d, -m1)) as dy", "sum(cast(m2 = 0 as long)) as ey",
    "sum(pow(2d, -greatest(m2, s_owner)) - pow(2d, -m1)) as dys", "sum(cast(greatest(m2, s_owner) = 0 as long)) as eys",
    "sum(cast(s as double) * s) as sq", "sum(s) as s",
)


def estimates(state: DataFrame, estimator: str = "smooth") -> DataFrame:
    """(b, kind, d, term, sq, s): the union's estimate and the sum of all sites' differences.

    The state has 2^b rows a kind, whatever the data, so it goes to one task, and there is no exchange after that.
    """
    est = ESTIMATES_SQL[estimator]
    owned = state.repartition(1).groupBy("b", "kind", "owner").agg(*map(F.expr, _OWNED))
    whole = owned.selectExpr("*", "shiftleft(1L, b) as m", "sum(cells) over (partition by b, kind) as full", "sum(p) over (partition by b, kind) as z0")
    whole = whole.selectExpr("*", "m - full as e", "z0 + (m - full) as z")
    rows = whole.selectExpr("b", "kind", "m", "z", "e", "sq", "s", f"{est('(z + dys)', '(e + eys)')} - {est('(z + dy)', '(e + ey)')} as term")
    one = rows.groupBy("b", "kind", "m", "z", "e").agg(F.expr("sum(term) as term"), F.expr("sum(sq) as sq"), F.expr("sum(s) as s"))
    return one.selectExpr("b", "kind", f"{est('z', 'e')} as d", "term", "sq", "s")


def evidence(summary: DataFrame, b: int | Sequence[int], estimator: str = "smooth", depth: int = 3) -> DataFrame:
    """One row for each b: b, n, d, f1, m2, d_res, f1_res, as far as the summary holds them; the rest null.

    f1 is the sum of differences of unions with and without each site's own singletons, kept within [0, d].
    """
    at = lambda size, kind, x: f"max(if(b = {size} and kind = {kind}, {x}, null))"

    def pair(size: int, kind: int) -> tuple[str, str]:
        d, f1 = at(size, kind, "d"), at(size, kind, "term")
        return d, f"if({f1} is null, null, greatest(0d, least({f1}, {d})))"

    rows = []
    for size in [b] if isinstance(b, int) else b:
        (d, f1), (d_res, f1_res) = pair(size, SAMPLE), pair(size, RESAMPLE)
        rows.append(f"named_struct('b', {size}, 'd', {d}, 'f1', {f1}, 'd_res', {d_res}, 'f1_res', {f1_res})")
    n = f"coalesce(max(if(kind = {ROWS}, s, null)), 0L) as n"
    m2 = f"percentile(if(kind between {COUNTERS} and {COUNTERS + depth - 1}, sq, null), 0.5) as m2"
    wide = estimates(union_state(summary), estimator).agg(F.expr(n), F.expr(m2), F.expr(f"array({', '.join(rows)}) as x"))
    return wide.selectExpr("n", "m2", "explode(x) as x").selectExpr("x.b", "n", "x.d", "x.f1", "m2", "x.d_res", "x.f1_res")


def sketched_evidence(sample: DataFrame, b: int | Sequence[int], needs: Iterable[str] = ("d", "f1", "m2", "d_res", "f1_res"), estimator: str = "smooth", **how) -> DataFrame:
    """From the sample to its evidence."""
    return evidence(site_summary(sample, b, needs, **how), b, estimator, how.get("depth", 3))


def registers(summary: DataFrame, kind: int = SAMPLE) -> DataFrame:
    """(site, reg, rd, r1) of an unpruned summary, for the other routes."""
    return summary.where(F.col("kind") == kind).groupBy("site", F.col("slot").alias("reg")).agg(F.max("rd").alias("rd"), F.max("r1").alias("r1"))


