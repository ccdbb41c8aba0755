"""Near-duplicate vectors with a robust-pruned flat graph over overlapping cluster shards.

1. Equal vectors of a label are one class, so large groups of copies cost one point.
2. Each label gets pivots, drawn from a bounded sample (``PIVOTS`` points of a cell at most) and settled by
   a few rounds of k-means; cells that stay too large are split again. A point lives in its nearest pivot's cell. As a
   query it visits its own cell and every other that may hold a point within the threshold: a point of cell p is nearer to
   p than to any other pivot, so a query that is farther than the link distance beyond the plane half way
   between p and its own pivot cannot have links there. This overlap of shards is exact, not a guess.
3. Cells are dealt into blocks of bounded size. Over each block's residents and visitors a flat graph is built:
   near neighbours of a point, thinned by robust pruning (a neighbour is dropped if a kept one is nearer to it
   than the point by a factor). A point stands in several overlapping shards; its lists are united.
4. Each query walks the united graph greedily from the block's medoids, then expands its range: all neighbours
   of points found within a widened threshold are looked at until no more turn up. Only points that the walk looks at are
   compared; links are what it finds, verified in double precision.
5. Recall is audited: some queries of each block are held against all its points. A block whose audit finds a link that the walk
   missed is completed, all its pairs compared (``completed``). ``graph_links`` beside ``n_links`` shows the walk's own part.
6. Links are weighed by their classes' sizes; blocks report for each query its number of links and the smallest
   point of its component there, never pairs; components are then merged over all blocks.

Cosines are taken in double precision. Defined results: a null label or a vector that is null, empty, zero or holds
a null or a non-finite component links with nothing (itself its component); vectors of different length don't link;
rows that repeat an id and its vector are one node; a null id links with nothing; an empty table gives an empty result.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import connected_components, small, stored

THRESHOLD = 0.98
#: Points of a block at most, about; sample and number of pivots of a label at most.
BLOCK = 5000
PIVOTS, MOST_CELLS, LEVELS = 4096, 256, 6
#: Points that share one copy of their cell's pivots; rows up to which a table of sizes is broadcast.
SALT, SMALL = 20_000, 20_000
#: A point's graph lists come from this many of its cells.
OVERLAP = 2
DEGREE, LONG, BEAM, MEDOIDS, NEAR, OCCLUSION = 16, 2, 12, 24, 48, 1.2
#: Numbers that a step of the Python side holds at once, about, whatever a block's density; queries that walk together.
HELD, TOGETHER = 1 << 20, 512
#: Range of the walk, as a multiple of the link angle; queries of a block that are held against all its points.
WIDE, AUDIT = 2.0, 48


def robust_prune(x: np.ndarray, degree: int = DEGREE, near: int = NEAR, occlusion: float = OCCLUSION) -> np.ndarray:
    """Neighbour lists (-1 where there is none) of unit rows.

    The nearest candidate is kept; candidates that are nearer to a kept one than to the point itself, by the
    factor, are dropped; and so on. Rows go in step, as many at a time as memory allows.
    """
    n = len(x)
    out = np.full((n, degree + LONG), -1, np.int64)
    if n < 2:
        return out
    # A few links at random keep clusters in reach of each other.
    out[:, degree:] = np.random.default_rng(n).integers(0, n, (n, LONG))
    m = min(near, n - 1)
    step = max(16, min(512, 2 * HELD // n))
    for at in range(0, n, step):
        rows = np.arange(min(step, n - at))
        sims = x[at : at + step] @ x.T
        sims[rows, at + rows] = -np.inf
        np.negative(sims, out=sims)
        cand = np.argpartition(sims, m - 1, axis=1)[:, :m]
        score = np.take_along_axis(sims, cand, 1)
        order = np.argsort(score, axis=1, kind="stable")
        cand, dist = np.take_along_axis(cand, order, 1), 2 + 2 * np.take_along_axis(score, order, 1)
        points, alive = x[cand], np.ones_like(cand, bool)
        for k in range(degree):
            some = alive.any(axis=1)
            if not some.any():
                break
            first = alive.argmax(axis=1)
            pick = cand[rows, first]
            out[at + rows[some], k] = pick[some]
            alive[rows, first] = False
            between = 2 - 2 * np.einsum("rd,rmd->rm", x[pick], points)
            alive &= occlusion * between > dist
    return out


def both_ways(n: int, src: np.ndarray, dst: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Adjacency as sorted (starts, targets) with each edge in both directions."""
    e = np.unique(np.concatenate((src * n + dst, dst * n + src)))
    return np.searchsorted(e // n, np.arange(n + 1)), e % n


def edges_of(lists: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    a, k = np.nonzero(lists >= 0)
    return a, lists[a, k]


def medoids_of(points: np.ndarray, most: int = MEDOIDS) -> np.ndarray:
    """The medoid, then again and again the point that is farthest from those taken: where walks start."""
    picks = [int((points @ points.sum(axis=0)).argmax())]
    near = points @ points[picks[0]]
    while len(picks) < min(most, len(points)):
        picks.append(int(near.argmin()))
        near = np.maximum(near, points @ points[picks[-1]])
    return np.unique(picks)


def walk(adj: tuple[np.ndarray, np.ndarray], points: np.ndarray, queries: np.ndarray, medoids: np.ndarray, wide: float, beam: int = BEAM) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(query, point, similarity) of all that the walk found at ``wide`` or nearer; other points are never compared.

    Greedy steps from the medoids expand the best unexpanded point while it is among the ``beam`` best; then the range is
    expanded: neighbours of every point found within ``wide`` are looked at until no more turn up.
    """
    starts, targets = adj
    q, n = len(queries), len(points)
    seen, done = np.zeros((q, n), bool), np.zeros((q, n), bool)
    found: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []

    def look(rows: np.ndarray, xs: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Compare the neighbours of (row, point) pairs that these rows haven't seen."""
        counts = starts[xs + 1] - starts[xs]
        own = np.repeat(rows, counts)
        first = np.repeat(starts[xs] - np.concatenate(([0], np.cumsum(counts)[:-1])), counts)
        near = targets[first + np.arange(len(own))]
        done[rows, xs] = True
        fresh = ~seen[own, near]
        own, near = own[fresh], near[fresh]
        seen[own, near] = True
        return compare(own, near)

    def compare(own: np.ndarray, near: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        sims = np.empty(len(own), points.dtype)
        for at in range(0, len(own), 65536):
            part = slice(at, at + 65536)
            np.einsum("ij,ij->i", queries[own[part]], points[near[part]], out=sims[part])
        ok = sims >= wide
        if ok.any():
            found.append((own[ok].astype(np.int32), near[ok].astype(np.int32), sims[ok]))
        return own, near, sims

    active, width = np.arange(q), max(min(beam, n), len(medoids))
    seen[:, medoids] = True
    best_id = np.full((q, width), -1)
    best = np.full((q, width), -np.inf, points.dtype)
    best_id[:, : len(medoids)] = medoids
    best[:, : len(medoids)] = compare(np.repeat(active, len(medoids)), np.tile(medoids, q))[2].reshape(q, -1)
    width = min(beam, n)
    keep = np.argpartition(-best, width - 1, axis=1)[:, :width]
    best, best_id = np.take_along_axis(best, keep, 1), np.take_along_axis(best_id, keep, 1)
    while len(active):
        ids = best_id[active]
        left = np.where((ids < 0) | done[active[:, None], ids], -np.inf, best[active])
        pick = left.argmax(axis=1)
        go = left[np.arange(len(active)), pick] > -np.inf
        active, pick = active[go], pick[go]
        if not len(active):
            break
        own, near, sims = look(active, best_id[active, pick])
        if not len(own):
            continue
        # The new ones stand beside the beam, a row each; the best of both stay.
        place = np.searchsorted(active, own)
        at = np.arange(len(own)) - np.searchsorted(own, active)[place]
        most = int(at.max()) + 1
        more, more_id = np.full((len(active), most), -np.inf, points.dtype), np.full((len(active), most), -1)
        more[place, at], more_id[place, at] = sims, near
        both, both_id = np.concatenate((best[active], more), axis=1), np.concatenate((best_id[active], more_id), axis=1)
        keep = np.argpartition(-both, width - 1, axis=1)[:, :width]
        best[active], best_id[active] = np.take_along_axis(both, keep, 1), np.take_along_axis(both_id, keep, 1)
    at = 0
    while at < len(found):
        rows, xs, _ = found[at]
        at += 1
        open_ = ~done[rows, xs]
        rows, xs = rows[open_].astype(np.int64), xs[open_].astype(np.int64)
        done[rows, xs] = True
        # In a crowd every point has found all others: their neighbours are looked at in slices of bounded size.
        ends = np.cumsum(starts[xs + 1] - starts[xs])
        low = 0
        while low < len(rows):
            high = max(low + 1, int(np.searchsorted(ends, (ends[low - 1] if low else 0) + HELD, side="right")))
            r, x = rows[low:high], xs[low:high]
            low = high
            counts = starts[x + 1] - starts[x]
            own = np.repeat(r, counts)
            first = np.repeat(starts[x] - np.concatenate(([0], np.cumsum(counts)[:-1])), counts)
            near = targets[first + np.arange(len(own))]
            # A point may be a neighbour of several: each pair once.
            key = np.unique((own * n + near)[~seen[own, near]])
            own, near = key // n, key % n
            seen[own, near] = True
            compare(own, near)
    if not found:
        none = np.zeros(0, np.int32)
        return none, none, none.astype(points.dtype)
    return tuple(np.concatenate(x) for x in zip(*found, strict=True))


def link_block(
    res: np.ndarray, res_id: np.ndarray, res_n: np.ndarray, edges: tuple[np.ndarray, np.ndarray], vis: np.ndarray, vis_id: np.ndarray, threshold: float,
    audit: int = AUDIT, complete: bool = True,
) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(links, links the walk found, smallest component id in the block) of each query.

    Residents (unit rows ``res``) are the points of the graph; queries are the residents and then the visitors. Links are what the
    walk finds, verified in double precision. ``audit`` queries are held against all residents; if the walk missed a link of
    theirs, the block's graph is not to be trusted, and with ``complete`` all its queries are held against all residents.
    """
    n = len(res)
    adj = both_ways(n, *edges)
    medoids = medoids_of(res)
    queries, ids = np.concatenate((res, vis)), np.concatenate((res_id, vis_id))
    # Single precision leads the walk; links are verified in double.
    rough, wide = res.astype(np.float32), np.float32(np.cos(min(np.pi, WIDE * np.arccos(threshold))))
    links = np.zeros((len(queries), -(-n // 8)), np.uint8)
    for at in range(0, len(queries), TOGETHER):
        part = queries[at : at + TOGETHER]
        q, x, sims = walk(adj, rough, part.astype(np.float32), medoids, wide)
        ok = sims >= threshold - 1e-4
        q, x = q[ok], x[ok]
        hit = np.zeros((len(part), n), bool)
        for some in range(0, len(q), 16_384):
            own, near = q[some : some + 16_384], x[some : some + 16_384]
            hit[own, near] = np.einsum("ij,ij->i", part[own], res[near]) >= threshold
        links[at : at + TOGETHER] = packed(hit, at)
    # Residents find each other: what one of them found is a link of both.
    mutual = np.unpackbits(links[:n], axis=1, count=n)
    mutual |= mutual.T.copy()
    links[:n] = np.packbits(mutual, axis=1)
    del mutual
    walked = weighed(links, res_n)
    total = walked
    some = np.unique(np.linspace(0, len(queries) - 1, min(audit, len(queries))).astype(np.int64))
    if complete and len(some):
        exact = queries[some] @ res.T >= threshold
        exact[some[:, None] == np.arange(n)] = False
        if (exact @ res_n != walked[some]).any():
            links = completed(queries, res, threshold)
            total = weighed(links, res_n)
    # The smallest label among linked points, both ways, until nothing changes.
    label, linked = ids.copy(), np.flatnonzero(links.any(axis=1))
    while len(linked):
        before = label.copy()
        for at in range(0, len(linked), TOGETHER // 2):
            own = linked[at : at + TOGETHER // 2]
            rows, xs = np.nonzero(np.unpackbits(links[own], axis=1, count=n))
            rows = own[rows]
            low = np.minimum(label[rows], label[xs])
            np.minimum.at(label, rows, low)
            np.minimum.at(label, xs, low)
        if (label == before).all():
            break
    return total, walked, label


def packed(hit: np.ndarray, at: int) -> np.ndarray:
    """Rows of links, a bit for each resident; the first row's query is number ``at``, and none links with itself."""
    own = np.arange(at, min(at + len(hit), hit.shape[1]))
    hit[own - at, own] = False
    return np.packbits(hit, axis=1)


def weighed(links: np.ndarray, res_n: np.ndarray) -> np.ndarray:
    """Each query's number of links, residents counted by their classes' sizes."""
    out, n = np.zeros(len(links), np.int64), res_n.astype(float)
    linked = np.flatnonzero(links.any(axis=1))
    for at in range(0, len(linked), TOGETHER):
        own = linked[at : at + TOGETHER]
        out[own] = (np.unpackbits(links[own], axis=1, count=len(n)).astype(float) @ n).astype(np.int64)
    return out


def completed(queries: np.ndarray, res: np.ndarray, threshold: float) -> np.ndarray:
    """The exact completion of a block whose audit failed: all its links at the threshold, as bits."""
    links = np.zeros((len(queries), -(-len(res) // 8)), np.uint8)
    for at in range(0, len(queries), TOGETHER):
        links[at : at + TOGETHER] = packed(queries[at : at + TOGETHER] @ res.T >= threshold, at)
    return links


def unit(x: np.ndarray) -> np.ndarray:
    return x / np.sqrt((x * x).sum(axis=1, keepdims=True))


def settled(points: np.ndarray, k: int, rounds: int = 4) -> np.ndarray:
    """k pivots of a sample by k-means from spread-out seeds."""
    r = np.random.default_rng(k)
    pivots = points[r.permutation(len(points))[:k]]
    for _ in range(rounds):
        near = (points @ pivots.T - 0.5 * (pivots * pivots).sum(axis=1)).argmax(axis=1)
        for c in range(len(pivots)):
            if (near == c).any():
                pivots[c] = points[near == c].mean(axis=0)
    return pivots


def classes(df: DataFrame, id_col: str, vector: str, label: str) -> DataFrame:
    """One row per distinct valid vector of a label: cls (smallest id), n (its ids), label, dim, vec."""
    v = F.col("vec")
    # Floats stay floats, half the bytes; they are compared as doubles.
    kind = "array<float>" if df.schema[vector].dataType.simpleString() == "array<float>" else "array<double>"
    good = df.select(F.col(id_col).cast("long").alias("id"), F.col(label).cast("string").alias("label"), F.col(vector).cast(kind).alias("vec"))
    # Other numbers may overflow a square or vanish in it: those count as not finite or as zero.
    norm = F.aggregate(v, F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double"))
    good = good.where("id is not null and label is not null and vec is not null")
    good = good.where((F.size(v) > 0) & ~F.exists(v, lambda x: x.isNull() | F.isnan(x)))
    good = good.where((norm > 0) & (norm < float("inf")))
    # Rows that repeat id and vector go first, so that an id counts once.
    once = good.groupBy("label", "vec", "id").agg(F.lit(1).alias("one"))
    return once.groupBy("label", "vec").agg(F.min("id").alias("cls"), F.count("*").alias("n")).withColumn("dim", F.size("vec"))


def placed(points: DataFrame, block: int, threshold: float) -> DataFrame:
    """(label, dim, cell, cls, n, vec, rank): each point as resident of its cell (rank 0), and as visitor, by rank, of the cells that may hold links of it.

    Cells of more than ``block`` residents are split again, each with pivots of its own, so that cells of a label grow in number with its points
    and no point is held against more than ``MOST_CELLS`` pivots a level. A cell that a split hardly made smaller stays as it is.
    """
    key, kind = ["label", "dim", "cell"], points.schema["vec"].dataType.simpleString()
    now = points.select("label", "dim", F.lit("").alias("cell"), "cls", "n", "vec", F.lit(0).alias("rank"), F.lit(1 << 62).alias("was"))
    for level in range(LEVELS):
        sizes = now.where("rank = 0").groupBy(*key, "was").agg(F.count("*").alias("size"))
        sizes = stored(sizes.where((F.col("size") > block) & (F.col("size") < 0.9 * F.col("was"))).drop("was"), "sizes")
        if not sizes.take(1):
            break
        split = dealt(now, small(sizes, SMALL), key, kind, block, threshold)
        now = stored(split, "placed")
    return now.drop("was")


def dealt(now: DataFrame, sizes: DataFrame, key: list[str], kind: str, block: int, threshold: float) -> DataFrame:
    """``now`` with the cells of ``sizes`` split; others pass."""
    marked = now.join(sizes, key, "left")
    h = F.xxhash64("cls")
    # A bounded sample by hash, so that the window sees few rows of any cell.
    few = marked.where("rank = 0 and size is not null").withColumn("h", h).where(F.pmod("h", F.lit(1 << 30)) < (1 << 30) * F.least(F.lit(1.0), 2.0 * PIVOTS / F.col("size")))
    order = Window.partitionBy(*key).orderBy("h", "cls")
    few = few.withColumn("k", F.row_number().over(order)).where(F.col("k") <= PIVOTS).select(*key, "size", "vec")

    def settle(t: pa.Table) -> pa.Table:
        x = vectors_of(t)
        cells = min(MOST_CELLS, len(x), -(-t["size"][0].as_py() // block))
        salts = -(-t["size"][0].as_py() // SALT)
        p = pa.array([settled(x, cells).ravel().tolist()] * salts, pa.list_(pa.float64()))
        keep = [pa.concat_arrays([t[c].combine_chunks()[:1]] * salts) for c in key]
        return pa.table([*keep, pa.array(range(salts), pa.int32()), p], names=[*key, "salt", "pivots"])

    # Each cell's pivots stand once at the head of each share of its points, not in every row.
    pivots = few.groupBy(*key).applyInArrow(settle, "label string, dim int, cell string, salt int, pivots array<double>")
    salt = F.when(F.col("size").isNull(), F.pmod(h, F.lit(64))).otherwise(F.pmod(h, F.ceil(F.col("size") / SALT))).cast("int")
    names = [*key, "salt", "pivots", "cls", "n", "vec", "rank", "was"]
    rows = marked.select(*key, salt.alias("salt"), F.lit(None).cast("array<double>").alias("pivots"), "cls", "n", "vec", "rank", F.coalesce("size", "was").alias("was"))
    heads = pivots.select(*key, "salt", "pivots", *[F.lit(None).cast(rows.schema[c].dataType).alias(c) for c in names[5:]])
    both = rows.unionByName(heads).repartition(*key, "salt").sortWithinPartitions(*key, "salt", F.col("pivots").isNull())
    slack = float(np.sqrt(2 - 2 * threshold)) + 1e-9

    def visits(part, splits, head, p, half, gap):
        """The part's rows in all cells that they visit, in batches of bounded size: in many dimensions a point may visit most cells."""
        if splits:
            v = unit(part.column(7).flatten().to_numpy().reshape(part.num_rows, head[1]).astype(float))
            s = v @ p.T - half
            best = s.argmax(axis=1)
            top = s[np.arange(len(s)), best][:, None]
            may = top - s <= slack * gap[best] + 1e-9
            place = np.argsort(np.argsort(np.where(may, -s, np.inf), axis=1, kind="stable"), axis=1)
            pick, cell = np.nonzero(may)
            rank = part.column(8).to_numpy()[pick] + place[pick, cell]
        else:
            pick, rank = np.arange(part.num_rows), part.column(8).to_numpy()
        for low in range(0, len(pick), 8192):
            some = slice(low, low + 8192)
            t = part.take(pa.array(pick[some], pa.int64()))
            cells = pa.array([f"{head[2]}.{c}" for c in cell[some].tolist()], pa.string()) if splits else t.column(2)
            yield pa.RecordBatch.from_arrays(
                [t.column(0), t.column(1), cells, t.column(5), t.column(6), t.column(7), pa.array(rank[some], pa.int32()), t.column(9)],
                names=["label", "dim", "cell", "cls", "n", "vec", "rank", "was"],
            )

    def deal(batches):
        head, p, half, gap = None, None, None, None
        for batch in batches:
            where = list(zip(*[batch.column(i).to_pylist() for i in range(4)], strict=True))
            is_head = np.asarray(batch.column(4).is_valid())
            starts = [i for i in range(len(where)) if not i or where[i] != where[i - 1]]
            for at, end in zip(starts, [*starts[1:], len(where)], strict=True):
                if is_head[at]:
                    head = where[at]
                    p = batch.column(4)[at].values.to_numpy().reshape(-1, head[1])
                    half = 0.5 * (p * p).sum(axis=1)
                    gap = np.sqrt(np.maximum(0, (2 * half)[:, None] + (2 * half)[None, :] - 2 * p @ p.T))
                    at += 1
                for low in range(at, end, 1024):
                    yield from visits(batch.slice(low, min(1024, end - low)), where[end - 1] == head, head, p, half, gap)

    return both.mapInArrow(deal, f"label string, dim int, cell string, cls long, n long, vec {kind}, rank int, was long")


def block_links(cells: DataFrame, block: int, threshold: float, complete: bool = True) -> DataFrame:
    """(cls, links, walked, root) of each query in each block of each cell."""
    key = ["label", "dim", "cell"]
    sizes = cells.groupBy(*key).agg(
        F.ceil(F.sum((F.col("rank") == 0).cast("int")) / block).cast("int").alias("parts"),
        F.ceil(F.count("*") / (4 * block)).cast("int").alias("rounds"),
        F.ceil(F.sum((F.col("rank") < OVERLAP).cast("int")) / (2 * OVERLAP * block)).cast("int").alias("shards"),
    )
    d = cells.join(small(stored(sizes.where("parts > 0"), "cells"), SMALL), key)
    # Residents of a large cell are dealt into parts; queries meet each part, and large crowds of queries
    # are dealt into rounds, each with its own copy of the part's residents.
    own = F.pmod(F.xxhash64("cls", F.lit(1)), F.col("parts"))
    turn = F.pmod(F.xxhash64("cls", F.lit(2)), F.col("rounds"))
    shard = F.pmod(F.xxhash64("cls", F.lit(1)), F.col("shards")).cast("int")
    lists = stored(united(d.where(F.col("rank") < OVERLAP).withColumn("part", shard), key), "lists")
    # A resident asks in its own block; all others come as guests.
    asks = d.withColumn("part", F.explode(F.sequence(F.lit(0), F.col("parts") - 1))).where((F.col("rank") > 0) | (F.col("part") != own)).withColumn("round", turn.cast("int"))
    none = F.lit(None).cast("array<long>")
    asks = asks.select(*key, "part", "round", "cls", "n", "vec", F.lit(False).alias("base"), F.lit(True).alias("asked"), none.alias("near"))
    base = d.where("rank = 0").join(lists, ["label", "dim", "cls"], "left")
    base = base.withColumn("part", own.cast("int")).withColumn("round", F.explode(F.sequence(F.lit(0), F.col("rounds") - 1)))
    base = base.select(*key, "part", "round", "cls", "n", "vec", F.lit(True).alias("base"), (F.col("round") == turn).alias("asked"), "near")

    def run(t: pa.Table) -> pa.Table:
        x = vectors_of(t)
        base, asked, ids, n = (t[c].to_numpy() for c in ("base", "asked", "cls", "n"))
        here = np.flatnonzero(base)
        here = here[np.argsort(ids[here], kind="stable")]
        guests = np.flatnonzero(~base)
        near = t["near"].combine_chunks().take(pa.array(here))
        src = np.repeat(np.arange(len(here)), near.value_lengths().fill_null(0).to_numpy())
        other = near.flatten().to_numpy()
        # Neighbours of other shards that aren't points of this block are left out.
        place = np.minimum(np.searchsorted(ids[here], other), max(0, len(here) - 1))
        inside = ids[here][place] == other if len(here) else np.zeros(0, bool)
        links, walked, root = link_block(x[here], ids[here], n[here], (src[inside], place[inside]), x[guests], ids[guests], threshold, complete=complete)
        order = np.concatenate((here, guests))
        # Residents that ask in another round only lend their component.
        every, counts = ids[order], asked[order]
        return pa.table({"cls": every, "links": np.where(counts, links, 0), "walked": np.where(counts, walked, 0), "root": root})

    return (
        asks.unionByName(base)
        .groupBy(*key, "part", "round")
        .applyInArrow(run, "cls long, links long, walked long, root long")
    )


def vectors_of(t: pa.Table) -> np.ndarray:
    return unit(t["vec"].combine_chunks().values.to_numpy().reshape(t.num_rows, t["dim"][0].as_py()).astype(float))


def united(dealt: DataFrame, key: list[str]) -> DataFrame:
    """(label, dim, cls, near): each point's pruned neighbours from all shards that it stands in."""

    def build(t: pa.Table) -> pa.Table:
        x, ids = vectors_of(t), t["cls"].to_numpy()
        lists = robust_prune(x)
        near = [ids[row[row >= 0]].tolist() for row in lists]
        return pa.table({"label": t["label"], "dim": t["dim"], "cls": ids, "near": pa.array(near, pa.list_(pa.int64()))})

    shards = dealt.groupBy(*key, "part").applyInArrow(build, "label string, dim int, cls long, near array<long>")
    return shards.groupBy("label", "dim", "cls").agg(F.array_distinct(F.flatten(F.collect_list("near"))).alias("near"))


def near_vectors(
    df: DataFrame, id_col: str = "vec_id", vector: str = "embedding", label: str = "label", threshold: float = THRESHOLD, block: int = BLOCK, complete: bool = True
) -> DataFrame:
    """One row per input row: id, n_links, component_id, kept, and graph_links, the links the walk itself found."""
    points = stored(classes(df, id_col, vector, label), "points")
    found = stored(block_links(placed(points, block, threshold), block, threshold, complete), "blocks")
    sums = found.groupBy("cls").agg(F.sum("links").alias("links"), F.sum("walked").alias("walked"))
    roots = connected_components(found.where("cls <> root").select(F.col("cls").alias("u"), F.col("root").alias("v")))
    info = points.join(sums, "cls").join(roots, F.col("cls") == F.col("node"), "left")
    info = info.select(
        F.col("label").alias("__label"), F.col("vec").alias("__vec"), F.col("n").alias("__n"), "links", "walked", F.coalesce("root", "cls").alias("__root")
    )
    rows = df.select(
        F.col(id_col), F.col(label).cast("string").alias("__l"), F.col(vector).cast(points.schema["vec"].dataType).alias("__v")
    )
    out = rows.join(info, (F.col("__l") == F.col("__label")) & (F.col("__v") == F.col("__vec")) & F.col(id_col).isNotNull(), "left")
    return out.select(
        F.col(id_col),
        F.coalesce(F.col("links") + F.col("__n") - 1, F.lit(0)).cast("long").alias("n_links"),
        F.coalesce(F.col("__root"), F.col(id_col).cast("long")).alias("component_id"),
        F.coalesce(F.coalesce(F.col("__root"), F.col(id_col).cast("long")) == F.col(id_col), F.lit(True)).alias("kept"),
        F.coalesce(F.col("walked") + F.col("__n") - 1, F.lit(0)).cast("long").alias("graph_links"),
    )
