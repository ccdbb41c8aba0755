"""Mixing sources to target weights by hierarchical budgeting.

A tree of groups (domain, language, source) shares a token budget. Each node hands its budget to its
children by weight; a child that cannot use its share (its tokens times ``epochs``) leaves the shortage to
its siblings, by weight again, and only what the siblings cannot use is missed by the parent, whose own
siblings take it up. Since a node's capacity is the sum of its leaves' capacities, filling each level
to one water level from the top does exactly this. All amounts are whole numbers, so the result
does not depend on the order of additions.

Each leaf then takes a prefix of its seeded epochs: in every epoch its documents stand in the order of a
hash of seed, epoch and id; whole epochs are taken first, then documents of the last epoch until the budget
is met (the last one is taken in part, ``taken_tokens``). The prefix sums of a leaf are made in two steps,
over hash ranges and then within the one range that holds the cut, so that no leaf, however large,
is sorted in one task.

Defined results: null groups count as the group ``unknown``; null or empty texts have no tokens and are
never taken; rows that repeat an id are told apart by their text, rows equal in both are drawn together and the last
counts them all; an empty table gives an empty result; other columns pass untouched.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import BLANKS, stored

SEED = 11
EPOCHS = 2
#: The budget is this share of all tokens, in thousandths.
BUDGET_PER_MILLE = 1000
RANGES = 256
#: A word with the blanks before it.
LEADING = r"[\x20\x09-\x0D]*[^\x20\x09-\x0D]+"
LEVELS = ("domain", "language", "source")
#: Weights of domains by name; other domains, all languages and all sources weigh 1.
DOMAIN_WEIGHTS = {"web": 4, "books": 3, "code": 2, "forum": 1}
DOMAINS = ("web", "books", "code", "forum")


def domain_of(source: Column) -> Column:
    """The domain of a source: by the number at its end, modulo the number of domains."""
    tail = F.regexp_extract(source, r"([0-9]{1,6})$", 1)
    return F.when(tail == "", F.lit("unknown")).otherwise(
        F.get(F.array(*[F.lit(d) for d in DOMAINS]), F.try_to_number(tail, F.lit("999999")).cast("int") % len(DOMAINS))
    )


def tagged(df: DataFrame, id_col: str, text: str, lang: str, source: str, seed: int) -> DataFrame:
    """The rows with tree columns, tokens, and a key for hashing (all named ``__...``)."""
    d = df.withColumns(
        {
            "__source": F.coalesce(F.col(source).cast("string"), F.lit("unknown")),
            "__language": F.coalesce(F.col(lang).cast("string"), F.lit("unknown")),
            "__tokens": F.size(F.array_remove(F.split(F.coalesce(F.col(text), F.lit("")), BLANKS), "")).cast("long"),
        }
    )
    return d.withColumns({"__domain": domain_of(F.col("__source"))})


def place(id_col: str, seed: int, epoch: int) -> Column:
    """Position of a document in a seeded epoch: 48 bits of a digest."""
    return F.conv(F.substring(F.md5(F.concat_ws("|", F.lit(str(seed)), F.lit(str(epoch)), F.col(id_col).cast("string"))), 1, 12), 16, 10).cast("long")


def filled(nodes: DataFrame, parent: list[str], budget: Column) -> DataFrame:
    """Share each parent's budget among its children: cap, w and budget become ``given``.

    Children in ascending order of cap / w are full up to the water level. At child i the level would be
    (budget - cap before i) / (weight from i on); those whose own ratio is above it share it by weight.
    """
    order = [(F.col("cap").cast("decimal(38,12)") / F.col("w")), F.col("w"), *[F.col(c) for c in nodes.columns if c in LEVELS]]
    w = Window.partitionBy(*parent) if parent else Window.partitionBy(F.lit(0))
    up = w.orderBy(*order)
    d = nodes.withColumn("budget", budget)
    d = d.withColumn("before", F.sum("cap").over(up.rowsBetween(Window.unboundedPreceding, -1)))
    d = d.withColumn("before", F.coalesce("before", F.lit(0)).cast("long"))
    d = d.withColumn("weight", F.sum("w").over(up.rowsBetween(0, Window.unboundedFollowing)).cast("long"))
    big = lambda c: F.col(c).cast("decimal(19,0)")
    full = big("cap") * big("weight") <= F.greatest(big("budget") - big("before"), F.lit(0).cast("decimal(20,0)")) * big("w")
    d = d.withColumn("is_full", full)
    # The level is that of the first child that isn't full.
    first = Window.partitionBy(*(parent or [F.lit(0)]))
    at = F.min(F.when(~F.col("is_full"), F.struct((F.col("cap") / F.col("w")).alias("r"), "before", "weight"))).over(first)
    d = d.withColumn("cut", at)
    given = F.when(
        F.col("is_full") | F.col("cut").isNull(), F.col("cap")
    ).otherwise(F.expr("cast(((budget - cut.before) * cast(w as decimal(19,0))) div cut.weight as long)"))
    return d.withColumn("given", F.least(F.col("cap"), F.greatest(given, F.lit(0)))).drop("before", "weight", "is_full", "cut", "budget")


def budgets(leaves: DataFrame, per_mille: int = BUDGET_PER_MILLE, epochs: int = EPOCHS, weights: dict[str, int] | None = None) -> DataFrame:
    """(domain, language, source, tokens) -> the same with ``given``. As many rows as there are leaves."""
    weights = DOMAIN_WEIGHTS if weights is None else weights
    one = F.lit(1).cast("long")
    by_name = one
    for k, v in weights.items():
        by_name = F.when(F.col("domain") == k, F.lit(v).cast("long")).otherwise(by_name)
    leaves = leaves.withColumn("cap", (F.col("tokens") * epochs).cast("long"))
    langs = leaves.groupBy("domain", "language").agg(F.sum("cap").alias("cap"))
    total = leaves.agg((F.sum("tokens") * per_mille / 1000).cast("long").alias("budget"))
    tops = langs.groupBy("domain").agg(F.sum("cap").alias("cap")).withColumn("w", by_name).crossJoin(F.broadcast(total))
    tops = filled(tops, [], F.col("budget")).select("domain", F.col("given").alias("budget"))
    mids = langs.join(tops, "domain").withColumn("w", one)
    mids = filled(mids, ["domain"], F.col("budget")).select("domain", "language", F.col("given").alias("budget"))
    low = leaves.join(mids, ["domain", "language"]).withColumn("w", one)
    return filled(low, ["domain", "language"], F.col("budget")).select(*LEVELS, "tokens", "given")


def mix(
    df: DataFrame,
    id_col: str = "doc_id",
    text: str = "text",
    lang: str = "lang",
    source: str = "source",
    per_mille: int = BUDGET_PER_MILLE,
    epochs: int = EPOCHS,
    seed: int = SEED,
    weights: dict[str, int] | None = None,
) -> DataFrame:
    """Rows (id, domain, language, source, epoch, n_tokens, taken_tokens), one for each draw of a document."""
    return _draws(df, id_col, text, lang, source, per_mille, epochs, seed, weights).drop("tkey")


def _draws(
    df: DataFrame, id_col: str, text: str, lang: str, source: str, per_mille: int, epochs: int, seed: int, weights: dict[str, int] | None
) -> DataFrame:
    """The rows of ``mix`` with the hash of the text, ``tkey``."""
    narrow = tagged(df.select(*dict.fromkeys([id_col, text, lang, source])), id_col, text, lang, source, seed)
    narrow = narrow.where("__tokens > 0").select(
        F.col(id_col).alias("doc"),
        F.xxhash64(text).alias("tkey"),
        F.col("__domain").alias("domain"),
        F.col("__language").alias("language"),
        F.col("__source").alias("source"),
        F.col("__tokens").alias("n"),
        *[place(id_col, seed, e).alias(f"p{e}") for e in range(epochs)],
    )
    narrow = stored(narrow, "mix")
    leaves = narrow.groupBy(*LEVELS).agg(F.sum("n").alias("tokens"))
    plan = budgets(leaves, per_mille, epochs, weights)
    plan = plan.select(
        *LEVELS,
        F.expr("cast(given div tokens as int)").alias("whole"),
        F.expr("given % tokens").cast("long").alias("rest"),
    )
    plan = stored(plan, "budgets")
    spots = F.get(F.array(*[F.col(f"p{e}") for e in range(epochs)]), F.least("whole", F.lit(epochs - 1)))
    last = narrow.join(plan, list(LEVELS)).where((F.col("rest") > 0) & (F.col("whole") < epochs)).withColumn("spot", spots)
    last = last.withColumn("range", F.shiftright("spot", 40).cast("int"))
    sums = last.groupBy(*LEVELS, "range", "rest").agg(F.sum("n").alias("n"))
    up = Window.partitionBy(*LEVELS).orderBy("range").rowsBetween(Window.unboundedPreceding, -1)
    sums = sums.withColumn("before", F.coalesce(F.sum("n").over(up), F.lit(0)).cast("long"))
    # The one range of each leaf in which the budget ends.
    ends = sums.where("before < rest and before + n >= rest").select(*LEVELS, F.col("range").alias("end"), "before")
    ends = stored(ends, "ends")
    last = last.join(ends, list(LEVELS))
    sure = last.where("range < end").select(*LEVELS, "doc", "tkey", "n", F.col("whole").alias("epoch"), F.col("n").alias("taken"))
    within = Window.partitionBy(*LEVELS).orderBy("spot", "doc", "tkey").rowsBetween(Window.unboundedPreceding, -1)
    edge = last.where("range = end").withColumn("at", F.col("before") + F.coalesce(F.sum("n").over(within), F.lit(0)))
    edge = edge.where("at < rest").select(
        *LEVELS, "doc", "tkey", "n", F.col("whole").alias("epoch"), F.least(F.col("n"), F.col("rest") - F.col("at")).alias("taken")
    )
    rounds = narrow.join(plan, list(LEVELS)).where("whole > 0")
    rounds = rounds.select(*LEVELS, "doc", "tkey", "n", F.explode(F.sequence(F.lit(0), F.col("whole") - 1)).alias("epoch"), F.col("n").alias("taken"))
    out = rounds.unionByName(sure).unionByName(edge)
    return out.select(
        F.col("doc").alias(id_col), *LEVELS, F.col("epoch").cast("long").alias("epoch"), F.col("n").alias("n_tokens"), F.col("taken").cast("long").alias("taken_tokens"), "tkey"
    )


def drawn(
    df: DataFrame,
    id_col: str = "doc_id",
    text: str = "text",
    lang: str = "lang",
    source: str = "source",
    per_mille: int = BUDGET_PER_MILLE,
    epochs: int = EPOCHS,
    seed: int = SEED,
    weights: dict[str, int] | None = None,
) -> DataFrame:
    """``df``'s rows as often as the mix draws them, in their own columns; the document in which a leaf's budget ends is cut after its last taken word.

    Rows are told apart by id (null is an id too), text and leaf; those equal in all get the most draws of any of them."""
    draws = _draws(df, id_col, text, lang, source, per_mille, epochs, seed, weights)
    keys = [F.col("tkey").alias("__t_key"), *[F.col(c).alias(f"__t_{c}") for c in LEVELS]]
    times = draws.groupBy(F.col(id_col).alias("__t_id"), *keys).agg(F.max(F.struct("epoch", F.col("taken_tokens").alias("taken"))).alias("__last"))
    d = tagged(df, id_col, text, lang, source, seed).withColumn("__key", F.xxhash64(text))
    same = d[id_col].eqNullSafe(F.col("__t_id"))
    for c in ("key", *LEVELS):
        same = same & (F.col(f"__{c}") == F.col(f"__t_{c}"))
    d = d.join(times, same).withColumn("__draw", F.explode(F.sequence(F.lit(0).cast("long"), F.col("__last.epoch"))))
    cut = (F.col("__draw") == F.col("__last.epoch")) & (F.col("__last.taken") < F.col("__tokens"))
    short = F.array_join(F.slice(F.regexp_extract_all(text, F.lit(LEADING), F.lit(0)), F.lit(1), F.greatest(F.lit(1), F.col("__last.taken")).cast("int")), "")
    return d.select(*[F.when(cut, short).otherwise(F.col(c)).alias(c) if c == text else F.col(c) for c in df.columns])


#: The same in DuckDB SQL, for the given tables; test of every step in integers.
def oracle(per_mille: int = BUDGET_PER_MILLE, epochs: int = EPOCHS, seed: int = SEED, docs: str = "documents") -> str:
    weights = " ".join(f"WHEN '{k}' THEN {v}" for k, v in DOMAIN_WEIGHTS.items())
    names = ", ".join(f"'{d}'" for d in DOMAINS)
    places = ", ".join(f"('0x' || substr(md5('{seed}|{e}|' || CAST(doc_id AS VARCHAR)), 1, 12))::BIGINT AS p{e}" for e in range(epochs))
    spots = "[" + ", ".join(f"p{e}" for e in range(epochs)) + "]"

    def level(name: str, source: str, parent: str, keys: str) -> str:
        part = f"PARTITION BY {parent} " if parent else ""
        sort = f"ORDER BY CAST(cap AS DECIMAL(38,12)) / w, w, {keys}"
        return f"""
 {name}_a AS (SELECT *, coalesce(sum(cap) OVER ({part}{sort} ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::HUGEINT AS before,
   (sum(w) OVER ({part}{sort} ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING))::HUGEINT AS weight FROM {source}),
 {name}_b AS (SELECT *, cap::HUGEINT * weight <= greatest(budget::HUGEINT - before, 0) * w AS is_full FROM {name}_a),
 {name}_c AS (SELECT *, min(before) FILTER (NOT is_full) OVER ({part}) AS cut_before, max(weight) FILTER (NOT is_full) OVER ({part}) AS cut_weight FROM {name}_b),
 {name} AS (SELECT *, CASE WHEN is_full OR cut_before IS NULL THEN cap
   ELSE least(cap, greatest(((budget::HUGEINT - cut_before) * w) // cut_weight, 0)) END::BIGINT AS given FROM {name}_c)"""

    return f"""WITH d0 AS (SELECT doc_id, coalesce(source, 'unknown') AS source, coalesce(lang, 'unknown') AS language,
   len(regexp_extract_all(coalesce(text, ''), '[^\\x20\\x09-\\x0D]+'))::BIGINT AS n, {places} FROM {docs}),
 d AS (SELECT *, CASE WHEN regexp_extract(source, '([0-9]{{1,6}})$', 1) = '' THEN 'unknown'
   ELSE ([{names}])[(regexp_extract(source, '([0-9]{{1,6}})$', 1)::INTEGER % {len(DOMAINS)}) + 1] END AS domain FROM d0 WHERE n > 0),
 leaves AS (SELECT domain, language, source, sum(n)::BIGINT AS tokens, (sum(n) * {epochs})::BIGINT AS cap FROM d GROUP BY ALL),
 langs AS (SELECT domain, language, sum(cap)::BIGINT AS cap FROM leaves GROUP BY ALL),
 top0 AS (SELECT domain, sum(cap)::BIGINT AS cap, CASE domain {weights} ELSE 1 END::BIGINT AS w,
   (SELECT (sum(tokens) * {per_mille}) // 1000 FROM leaves) AS budget FROM langs GROUP BY domain),{level("tops", "top0", "", "domain")},
 mid0 AS (SELECT l.*, 1::BIGINT AS w, t.given AS budget FROM langs l JOIN tops t USING (domain)),{level("mids", "mid0", "domain", "language")},
 low0 AS (SELECT l.*, 1::BIGINT AS w, m.given AS budget FROM leaves l JOIN mids m USING (domain, language)),{level("lows", "low0", "domain, language", "source")},
 plan AS (SELECT domain, language, source, (given // tokens)::BIGINT AS whole, given % tokens AS rest FROM lows),
 j AS (SELECT d.*, whole, rest FROM d JOIN plan USING (domain, language, source)),
 x AS (SELECT *, coalesce(sum(n) OVER (PARTITION BY domain, language, source ORDER BY ({spots})[least(whole, {epochs - 1}) + 1], doc_id
   ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS pos FROM j)
SELECT doc_id, domain, language, source, whole AS epoch, n AS n_tokens, least(n, rest - pos)::BIGINT AS taken_tokens FROM x WHERE rest > 0 AND whole < {epochs} AND pos < rest
UNION ALL
SELECT doc_id, domain, language, source, unnest(range(0, whole)) AS epoch, n AS n_tokens, n AS taken_tokens FROM j WHERE whole > 0"""
