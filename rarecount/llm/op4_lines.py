"""Line dedup by pairwise alignment.

Lines that two documents share seed the pair. A rare line (of ``SEED_WORDS`` words or more, in at most ``rare``
documents) pairs all its holders; a line that is more frequent, but long enough to be a block of its own, pairs every
holder with the first one (the smallest id), which is linear in the number of lines. Each pair is then aligned by
patience diff: lines that are unique in both anchor the alignment, the longest increasing run of anchors is
kept, and it is grown over equal neighbours. Aligned blocks of at least ``least_words`` words are deleted from the
later document (``n_aligned`` of the report counts their lines).

Alignment alone misses blocks of frequent short lines only, blocks that a document repeats, and blocks in
another order; every holder of a frequent line meets one partner only. A second pass completes it: runs of lines are
matched exactly, from each line the shortest run on, and the shortest run back, of at least ``least_words`` words. A
block that two documents share is covered by such runs of both (see ``runs``), and an aligned block is such a block, so
that in the end a line goes if, and only if, it lies in consecutive lines of at least ``least_words`` words that stand in
an earlier document too. Runs are two a line at most, and each is matched with its first holder only.

Lines are compared as they stand. Defined results: null texts stay null; a text whose lines all go
becomes empty, its row stays; rows that repeat an id are told apart by their text, and of rows equal in both
all are treated alike; null ids take no part; an empty table gives an empty result; other columns pass untouched.
"""

from __future__ import annotations

from bisect import bisect_left
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import BLANKS, NOT_BLANK, stored

RARE = 8
LEAST_WORDS = 20
SEED_WORDS = 4
#: Of the hash of a run.
PRIME = (1 << 61) - 1
BASE = 0x1D8AF6E2B94C7A35


def lines_of(text: Column) -> Column:
    return F.split(F.coalesce(text, F.lit("")), "\n", -1)


def patience(a: list[int], b: list[int]) -> list[tuple[int, int]]:
    """Aligned positions (in a, in b), increasing in both."""
    out: list[tuple[int, int]] = []
    todo = [(0, len(a), 0, len(b))]
    while todo:
        alo, ahi, blo, bhi = todo.pop()
        while alo < ahi and blo < bhi and a[alo] == b[blo]:
            out.append((alo, blo))
            alo, blo = alo + 1, blo + 1
        while alo < ahi and blo < bhi and a[ahi - 1] == b[bhi - 1]:
            ahi, bhi = ahi - 1, bhi - 1
            out.append((ahi, bhi))
        if alo == ahi or blo == bhi:
            continue
        once_a, once_b = _once(a, alo, ahi), _once(b, blo, bhi)
        both = sorted((i, once_b[x]) for x, i in once_a.items() if x in once_b)
        chain = _increasing(both)
        if not chain:
            continue
        at_a, at_b = alo, blo
        for i, j in [*chain, (ahi, bhi)]:
            # Between two anchors the search goes on, and equal neighbours join the block.
            todo.append((at_a, i, at_b, j))
            if i < ahi:
                out.append((i, j))
            at_a, at_b = i + 1, j + 1
    return sorted(out)


def _once(x: list[int], lo: int, hi: int) -> dict[int, int]:
    at: dict[int, int] = {}
    for i in range(lo, hi):
        at[x[i]] = -1 if x[i] in at else i
    return {k: i for k, i in at.items() if i >= 0}


def _increasing(pairs: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """The longest chain whose second members increase; the first ones are sorted."""
    tails: list[int] = []
    last: list[int] = []
    back: list[int] = []
    for k, (_, j) in enumerate(pairs):
        at = bisect_left(tails, j)
        back.append(last[at - 1] if at else -1)
        if at == len(tails):
            tails.append(j)
            last.append(k)
        else:
            tails[at], last[at] = j, k
    chain, k = [], last[-1] if last else -1
    while k >= 0:
        chain.append(pairs[k])
        k = back[k]
    return chain[::-1]


def blocks(aligned: list[tuple[int, int]], words: list[int], least: int) -> list[int]:
    """Positions in the later document that lie in aligned blocks of enough words."""
    out: list[int] = []
    run: list[int] = []
    before = None
    for i, j in [*aligned, (-9, -9)]:
        if before is not None and (i, j) != (before[0] + 1, before[1] + 1):
            if sum(words[x] for x in run) >= least:
                out += run
            run = []
        run.append(j)
        before = (i, j)
    return out


def runs(hs: list[int], ws: list[int], least: int) -> Iterator[tuple[int, int, int, int]]:
    """(hash, hash of the first line, start, last) of the shortest runs of at least ``least`` words from and up to each line.

    Every line of a block of so many words lies in one of these within the block: in the run from it, in the
    run up to it, or, if both would leave the block, in the run from the block's first line. Hashes are
    differences of a polynomial's prefixes, so blank lines without end cost no more than others.
    """
    n = len(hs)
    sums, codes, powers = [0], [0], [1]
    for h, w in zip(hs, ws, strict=True):
        sums.append(sums[-1] + w)
        codes.append((codes[-1] * BASE + h % PRIME + 1) % PRIME)
        powers.append(powers[-1] * BASE % PRIME)
    found = set()
    to = 0
    for i in range(n):
        while to < n and (to <= i or sums[to] - sums[i] < least):
            to += 1
        if to == i or sums[to] - sums[i] < least:
            break
        found.add((i, to - 1))
    at = 0
    for j in range(n):
        while at < j and sums[j + 1] - sums[at + 1] >= least:
            at += 1
        if sums[j + 1] - sums[at] >= least:
            found.add((at, j))
    for i, j in sorted(found):
        yield (codes[j + 1] - codes[i] * powers[j + 1 - i]) % PRIME, hs[i], i, j


def deletions(df: DataFrame, id_col: str, text: str, rare: int = RARE, least_words: int = LEAST_WORDS) -> DataFrame:
    """(doc, tkey, gone): sorted line positions to delete from rows with that id and text hash."""
    d = df.where(F.col(id_col).isNotNull() & F.col(text).isNotNull()).select(
        F.col(id_col).cast("long").alias("doc"), F.xxhash64(text).alias("tkey"), lines_of(F.col(text)).alias("lines")
    )
    d = d.select(
        "doc",
        "tkey",
        F.transform("lines", lambda x: F.xxhash64(x)).alias("hs"),
        F.transform("lines", lambda x: F.size(F.array_remove(F.split(x, BLANKS), ""))).alias("ws"),
    )
    # Rows that repeat both id and text are equal here; one of them is enough.
    d = stored(d.dropDuplicates(["doc", "tkey"]), "lines")
    one = d.select(
        "doc", "tkey", F.explode(F.array_distinct(F.filter(F.arrays_zip("hs", "ws"), lambda x: x["ws"] >= SEED_WORDS))).alias("x")
    ).select("doc", "tkey", F.col("x.hs").alias("h"), F.col("x.ws").alias("w"))
    first = (
        one.groupBy("h")
        .agg(F.count("*").alias("df"), F.min(F.struct("doc", "tkey")).alias("first"), F.max("w").alias("w"))
        .where((F.col("df") > 1) & ((F.col("w") >= least_words) | (F.col("df") <= rare)))
        .select("h", F.col("first.doc").alias("fdoc"), F.col("first.tkey").alias("fkey"), (F.col("df") <= rare).alias("few"))
    )
    # As a table of its own, so that the join shuffles both sides and can split those of a very common line.
    first = stored(first, "firsts")
    seeded = one.join(first, "h")
    star = seeded.where(~F.col("few") & ((F.col("doc") != F.col("fdoc")) | (F.col("tkey") != F.col("fkey")))).select("doc", "tkey", "fdoc", "fkey")
    pairs = star.unionByName(rare_pairs(seeded.where("few"))).distinct()
    ahead = d.select(F.col("doc").alias("fdoc"), F.col("tkey").alias("fkey"), F.col("hs").alias("fhs"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            gone = []
            for a, b, w in zip(batch.column(2).to_pylist(), batch.column(3).to_pylist(), batch.column(4).to_pylist(), strict=True):
                gone.append(blocks(patience(a, b), w, least_words))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(gone, pa.list_(pa.int32()))], names=["doc", "tkey", "gone"])

    aligned = (
        pairs.join(d.select("doc", "tkey", "hs", "ws"), ["doc", "tkey"])
        .join(ahead, ["fdoc", "fkey"])
        .select("doc", "tkey", "fhs", "hs", "ws")
        .mapInArrow(run, "doc long, tkey long, gone array<int>")
    )
    found = aligned.where(F.size("gone") > 0).withColumn("by", F.lit("pair")).unionByName(repeated(d, least_words).withColumn("by", F.lit("run")))
    # A document's pairs are as many as its seeds at most; their lines are united, pair by pair.
    lines = lambda x: F.array_distinct(F.flatten(F.collect_list(x)))
    return found.groupBy("doc", "tkey").agg(F.sort_array(lines("gone")).alias("gone"), F.size(lines(F.when(F.col("by") == "pair", F.col("gone")))).alias("aligned"))


def rare_pairs(holders: DataFrame) -> DataFrame:
    """(doc, tkey, fdoc, fkey): all pairs of holders of the same rare line, the later one first.

    A rare line has a bounded number of holders; lines of the same holders, as those of copies, make their pairs once."""
    sets = holders.groupBy("h").agg(F.sort_array(F.collect_list(F.struct("doc", "tkey"))).alias("at")).select("at").distinct()
    later = sets.select("at", F.explode(F.sequence(F.lit(2), F.size("at"))).alias("j"))
    both = later.select(F.element_at("at", F.col("j")).alias("b"), F.explode(F.slice("at", F.lit(1), F.col("j") - 1)).alias("a"))
    return both.select(F.col("b.doc").alias("doc"), F.col("b.tkey").alias("tkey"), F.col("a.doc").alias("fdoc"), F.col("a.tkey").alias("fkey"))


def repeated(d: DataFrame, least_words: int) -> DataFrame:
    """(doc, tkey, gone) from (doc, tkey, hs, ws): lines in runs that an earlier document holds."""

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = ["doc", "tkey", "h", "l", "start", "last"]
        types = [pa.int64()] * 4 + [pa.int32()] * 2
        for batch in batches:
            rows: list[tuple] = []
            for doc, key, hs, ws in zip(*[c.to_pylist() for c in batch.columns], strict=True):
                rows += [(doc, key, *x) for x in runs(hs, ws, least_words)]
                if len(rows) > 50000:
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), types, strict=True)], names=names)
                    rows = []
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), types, strict=True)], names=names)

    def merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            gone = []
            for spans in batch.column(2).to_pylist():
                lines: list[int] = []
                for x in sorted((s["start"], s["last"]) for s in spans):
                    lines += range(max(x[0], lines[-1] + 1 if lines else 0), x[1] + 1)
                gone.append(lines)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(gone, pa.list_(pa.int32()))], names=["doc", "tkey", "gone"])

    cuts = d.select("doc", "tkey", "hs", "ws").mapInArrow(cut, "doc long, tkey long, h long, l long, start int, last int")
    cuts = stored(cuts, "runs")
    first = cuts.groupBy("h", "l").agg(F.min(F.struct("doc", "tkey")).alias("first"), F.max(F.struct("doc", "tkey")).alias("end")).where("first < end")
    first = stored(first.select("h", "l", F.col("first.doc").alias("fdoc"), F.col("first.tkey").alias("fkey")), "run-firsts")
    later = cuts.join(first, ["h", "l"]).where((F.col("doc") != F.col("fdoc")) | (F.col("tkey") != F.col("fkey")))
    spans = later.groupBy("doc", "tkey").agg(F.collect_list(F.struct("start", "last")).alias("spans"))
    return spans.mapInArrow(merge, "doc long, tkey long, gone array<int>")


def with_deletions(df: DataFrame, id_col: str, text: str, **how) -> DataFrame:
    gone = deletions(df, id_col, text, **how).select(F.col("doc").alias("__doc"), F.col("tkey").alias("__tkey"), F.col("gone").alias("__gone"), F.col("aligned").alias("__aligned"))
    return df.join(gone, (F.col(id_col).cast("long") == F.col("__doc")) & (F.xxhash64(text) == F.col("__tkey")), "left")


def cleaned(text: str = "text") -> Column:
    kept = F.filter(F.split(F.col(text), "\n", -1), lambda x, i: ~F.array_contains(F.col("__gone"), i))
    return F.when(F.col("__gone").isNull(), F.col(text)).otherwise(F.array_join(kept, "\n"))


def dedup_lines(df: DataFrame, id_col: str = "doc_id", text: str = "text", **how) -> DataFrame:
    """``df`` with cleaned texts, in its own columns."""
    return with_deletions(df, id_col, text, **how).select(*[cleaned(text).alias(text) if c == text else F.col(c) for c in df.columns])


def report(df: DataFrame, id_col: str = "doc_id", text: str = "text", **how) -> DataFrame:
    """One row per input row: id, lines before, the deleted line positions, and the cleaned text."""
    d = with_deletions(df.select(id_col, text), id_col, text, **how)
    return d.select(
        id_col,
        F.when(F.col(text).isNull(), 0).otherwise(F.size(lines_of(F.col(text)))).cast("long").alias("n_lines"),
        F.coalesce(F.size("__gone"), F.lit(0)).cast("long").alias("n_deleted"),
        F.coalesce(F.array_join(F.col("__gone").cast("array<string>"), ","), F.lit("")).alias("deleted_lines"),
        F.coalesce("__aligned", F.lit(0)).cast("long").alias("n_aligned"),
        cleaned(text).alias(text),
    )
