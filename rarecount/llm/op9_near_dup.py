"""Near-duplicate texts by a multi-index Hamming join of min-wise signatures, with exact confirmation.

A signature holds ``k`` symbols of 16 bits, one for each min-hash. Two texts of similarity J differ in
each symbol with probability at most 1 - J, so the distance (differing symbols) of a linked pair
is binomial; ``distance`` is set so far out that a linked pair exceeds it about once in a million
at the very threshold, and far less above it. The join then finds *every* pair within that distance:
the symbols are split into chunks so that, by the pigeonhole principle, some chunk has at most one
differing symbol, and each chunk is keyed by its symbols with each one left out in turn, which
enumerates the allowed errors from both sides. Equal keys are candidates.

No group's pairs are all made. Texts with equal sets are one class, and keys with equal members are one key.
Within a key, first each member is held against the key's smallest id (linear), and confirmed links are
merged into components. Keys whose members are still in different components are looked at in blocks of
bounded size: in one round each member is held against the few nearest of other components, and after merging
again, in the last round, against all of other components that may be links. To that end each set also has
counts of its shingles in hashed bins: the sum of the lesser counts bounds the intersection from above, with
certainty, so pairs below the threshold hardly ever come to be compared as texts. Pairs
are confirmed on full shingle sets. A link inside a component adds nothing to the components, so none is lost.

Defined results: texts that are null or without words have an empty set and link with nothing; fewer
words than five are one shingle; rows that repeat an id are one node; a null id links with nothing and is kept;
an empty table gives an empty result; further columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import connected_components, small, stored
from .shingles import multipliers, shared, shingle_set, signature

SYMBOLS = 64
DISTANCE = 25
#: Bins of a set's bin counts, and the largest set for which they are used.
BINS, MOST_BINNED = 512, 50_000
NEAREST = 4
BLOCK = 2048
#: Keys (three longs a row) up to which their table is broadcast.
FEW_KEYS = 200_000
PERCENT = 85


def chunks(k: int = SYMBOLS, distance: int = DISTANCE) -> list[tuple[int, int]]:
    """(start, length) of chunks such that ``distance`` errors leave one chunk with at most one."""
    m = distance // 2 + 1
    cuts = [i * k // m for i in range(m + 1)]
    return [(lo, hi - lo) for lo, hi in zip(cuts, cuts[1:], strict=False)]


def signatures(df: DataFrame, id_col: str, text: str, k: int = SYMBOLS) -> DataFrame:
    """doc, n_shingles, set_id (128-bit digest of the whole set), sig and bins of every row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        a, b = multipliers(k)
        for batch in batches:
            size, key, sig, bins = [], [], [], []
            for t in batch.column(1):
                s = shingle_set(t.as_py())
                size.append(len(s))
                if len(s):
                    both = (s.sum(dtype=np.uint64), (s * (s >> np.uint64(7) | np.uint64(1))).sum(dtype=np.uint64))
                    key.append(np.array(both, np.uint64).tobytes())
                    sig.append(signature(s, a, b).tobytes())
                    bins.append(np.minimum(np.bincount(s >> np.uint64(55), minlength=BINS), 255).astype(np.uint8).tobytes())
                else:
                    key.append(None)
                    sig.append(None)
                    bins.append(None)
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array(size, pa.int64()), pa.array(key, pa.binary()), pa.array(sig, pa.binary()), pa.array(bins, pa.binary())],
                names=["doc", "n_shingles", "set_id", "sig", "bins"],
            )

    return df.select(F.col(id_col).cast("long").alias("doc"), F.col(text).alias("t")).mapInArrow(
        run, "doc long, n_shingles long, set_id binary, sig binary, bins binary"
    )


def keyed(reps: DataFrame, k: int, distance: int) -> DataFrame:
    """(key, doc, n): every chunk with every one of its symbols left out."""
    keys = []
    for c, (lo, width) in enumerate(chunks(k, distance)):
        for j in range(width):
            keys.append(
                F.xxhash64(
                    F.lit(c * 64 + j),
                    F.substring("sig", 2 * lo + 1, 2 * j),
                    F.substring("sig", 2 * (lo + j) + 3, 2 * (width - j - 1)),
                )
            )
    return reps.select("doc", "n", F.explode(F.array(*keys)).alias("key"))


def confirmed(pairs: DataFrame, texts: DataFrame, percent: int) -> DataFrame:
    """Those of the pairs (a, b) whose full sets are similar enough."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last: tuple = (None, None)
        for batch in batches:
            keep = []
            for one, x, y in zip(batch.column(0).to_pylist(), batch.column(2), batch.column(3), strict=True):
                if last[0] != one:
                    last = (one, shingle_set(x.as_py()))
                s, t = last[1], shingle_set(y.as_py())
                both = shared(s, t)
                keep.append(both > 0 and 100 * both >= percent * (len(s) + len(t) - both))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1)], names=["u", "v"]).filter(pa.array(keep, pa.bool_()))

    first = texts.select(F.col("doc").alias("a"), F.col("t").alias("ta"))
    second = texts.select(F.col("doc").alias("b"), F.col("t").alias("tb"))
    return (
        pairs.join(second, "b").join(first, "a").select("a", "b", "ta", "tb").mapInArrow(run, "u long, v long")
    )


def bound(x: tuple, y: tuple, distance: int, percent: int) -> np.ndarray:
    """Row by row: an upper bound of the similarity of pairs that may be links, and -1 for those that can't.

    x and y: sizes, signatures and bin counts; y may be one row for all.
    """
    (nx, sx, bx), (ny, sy, by) = x, y
    ny = np.broadcast_to(ny, nx.shape)
    out = np.full(len(nx), -1.0)
    fit = 100 * np.minimum(nx, ny) >= percent * np.maximum(nx, ny)
    hit = np.flatnonzero(fit)
    hit = hit[(sx[hit] != (sy[hit] if sy.ndim > 1 else sy)).sum(axis=1) <= distance]
    both = np.minimum(bx[hit], by[hit] if by.ndim > 1 else by).sum(axis=1, dtype=np.int64)
    both = np.where(np.maximum(nx[hit], ny[hit]) > MOST_BINNED, np.minimum(nx[hit], ny[hit]), both)
    out[hit] = np.where(100 * both >= percent * (nx[hit] + ny[hit] - both), both / np.maximum(1, nx[hit] + ny[hit] - both), -1.0)
    return out


def matrix(column, kind) -> np.ndarray:
    return np.frombuffer(b"".join(column.to_pylist()), kind).reshape(len(column), -1)


def within(pairs: DataFrame, reps: DataFrame, distance: int, percent: int) -> DataFrame:
    """Those of the pairs (a, b) whose signatures and bins allow a link."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                x, y = ((batch.column(i).to_numpy(), matrix(batch.column(i + 1), np.uint16), matrix(batch.column(i + 2), np.uint8)) for i in (2, 5))
                yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1)], names=["a", "b"]).filter(pa.array(bound(x, y, distance, percent) >= 0))

    one, two = (reps.select(F.col("doc").alias(k), *[F.col(c).alias(c + k) for c in ("n", "sig", "bins")]) for k in ("a", "b"))
    both = pairs.join(one, "a").join(two, "b").select("a", "b", "na", "siga", "binsa", "nb", "sigb", "binsb")
    return both.mapInArrow(run, "a long, b long")


def block_pairs(mixed: DataFrame, percent: int, distance: int, block: int, nearest: int | None) -> DataFrame:
    """Pairs from different components that may be links, found in blocks of each key's members.

    ``mixed`` has key, members (its size), doc, n, comp, sig, bins. A key with more than ``block`` members is dealt
    into numbered blocks, and each two blocks meet in a task of their own. With ``nearest``, only so many of each member.
    """
    parts = F.ceil(F.col("members") / block).cast("int")
    own = F.pmod(F.xxhash64("doc", "key"), parts).cast("int")
    dealt = mixed.withColumn("own", own).withColumn(
        "meets",
        F.transform(F.sequence(F.lit(0), parts - 1), lambda o: F.struct(F.least("own", o).alias("i"), F.greatest("own", o).alias("j"))),
    )
    dealt = dealt.select("key", "doc", "n", "comp", "sig", "bins", "own", F.explode("meets").alias("m"))

    def run(table: pa.Table) -> pa.Table:
        order = np.argsort(table["doc"].to_numpy(), kind="stable")
        doc, n, comp, own = (table[c].to_numpy()[order] for c in ("doc", "n", "comp", "own"))
        sig, bins = matrix(table["sig"], np.uint16)[order], matrix(table["bins"], np.uint8)[order]
        i, j = table["i"][0].as_py(), table["j"][0].as_py()
        left, right = [], []
        for at in range(len(doc)):
            fit = comp != comp[at]
            if nearest is None:
                fit[: at + 1] = False
            if i != j:
                fit &= own != own[at]
            hit = np.flatnonzero(fit)
            if len(hit):
                most = bound((n[hit], sig[hit], bins[hit]), (n[at], sig[at], bins[at]), distance, percent)
                hit, most = hit[most >= 0], most[most >= 0]
                if nearest is not None and len(hit) > nearest:
                    hit = hit[np.argsort(-most, kind="stable")[:nearest]]
                left += np.minimum(doc[at], doc[hit]).tolist()
                right += np.maximum(doc[at], doc[hit]).tolist()
        return pa.table({"a": pa.array(left, pa.int64()), "b": pa.array(right, pa.int64())})

    flat = dealt.select("key", F.col("m.i").alias("i"), F.col("m.j").alias("j"), "doc", "n", "comp", "own", "sig", "bins")
    return flat.groupBy("key", "i", "j").applyInArrow(run, "a long, b long").distinct()


def near_duplicates(
    df: DataFrame,
    id_col: str = "doc_id",
    text: str = "text",
    percent: int = PERCENT,
    symbols: int = SYMBOLS,
    distance: int = DISTANCE,
    block: int = BLOCK,
) -> DataFrame:
    """One row per input row: ``id_col``, n_shingles, component_id, kept."""
    rows = stored(signatures(df, id_col, text, symbols), "signatures")
    # Equal sets are one class; its smallest id stands for it.
    valid = rows.where("n_shingles > 0 and doc is not null")
    reps = valid.groupBy("set_id", F.col("n_shingles").alias("n")).agg(F.min("doc").alias("doc"), F.min("sig").alias("sig"), F.min("bins").alias("bins"))
    reps = stored(reps, "classes")
    keys = keyed(reps, symbols, distance)
    # Keys that share the same members (told by two sums of hashes) are one.
    h = F.xxhash64("doc")
    shared_keys = keys.groupBy("key").agg(
        F.count("*").alias("members"), F.min("doc").alias("first"), F.bit_xor(h).alias("h1"), F.sum(F.shiftrightunsigned(h, 33)).alias("h2")
    )
    shared_keys = shared_keys.where("members > 1").groupBy("members", "first", "h1", "h2").agg(F.min("key").alias("key"))
    # Up to a size, keys aren't dealt out by value, so that one that very many hold makes no large task; above, a skewed join is split.
    shared_keys = small(stored(shared_keys.select("key", "members", "first"), "shared"), FEW_KEYS)
    many = stored(keys.join(shared_keys, "key").select("key", "members", "first", "doc", "n"), "keys")

    texts = df.where(F.col(id_col).isNotNull()).select(F.col(id_col).cast("long").alias("doc"), F.col(text).alias("t"))
    star = many.where("doc <> first").select(F.col("first").alias("a"), F.col("doc").alias("b")).distinct()
    links = stored(confirmed(within(star, reps, distance, percent), texts, percent), "links")
    for nearest in (NEAREST, None):
        merged = connected_components(links)
        comp = many.join(merged, many["doc"] == merged["node"], "left").select("key", "members", "doc", "n", F.coalesce("root", "doc").alias("comp"))
        open_keys = comp.groupBy("key").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi")).where("lo <> hi").select("key")
        mixed = comp.join(small(stored(open_keys, "open"), FEW_KEYS), "key").join(reps.select("doc", "sig", "bins"), "doc")
        more = stored(confirmed(block_pairs(mixed, percent, distance, block, nearest), texts, percent), "links")
        links = links.unionByName(more)
    copies = valid.select("doc", "set_id", F.col("n_shingles").alias("n"))
    copies = copies.join(reps.select("set_id", "n", F.col("doc").alias("v")), ["set_id", "n"]).select(F.col("doc").alias("u"), "v").where("u <> v")
    edges = links.unionByName(copies)
    roots = connected_components(edges)
    out = rows.select("doc", "n_shingles").join(roots, F.col("doc") == F.col("node"), "left")
    out = out.select(F.col("doc").alias(id_col), "n_shingles", F.coalesce("root", "doc").alias("component_id"))
    return out.withColumn("kept", F.coalesce(F.col(id_col) == F.col("component_id"), F.lit(True)))


def keep_first(df: DataFrame, id_col: str = "doc_id", text: str = "text", **how) -> DataFrame:
    """The rows of ``df`` without later members of a group; of rows that repeat a text and id, all stay."""
    gone = near_duplicates(df, id_col, text, **how).where("not kept").select(F.col(id_col).alias("__gone")).distinct()
    return df.join(gone, df[id_col] == F.col("__gone"), "left_anti")
