"""Quality by weak supervision: rules vote or abstain, expectation-maximisation weighs them.

Every rule looks at a few counts of a text and votes good (1), bad (-1) or abstains (0). The votes of
all documents are reduced to counts of vote patterns, of which there are at most 3 to the number
of rules, whatever the corpus. On these counts expectation-maximisation estimates how often each rule
votes rightly for good and for bad documents; the posterior probability of a document then follows
from its votes as a sum of constants, inside the scan.

Defined results: a null text counts as an empty one and fails the base rule, as do texts of fewer
than 50 words; an empty table gives an empty result; repeated rows are each judged; other columns
pass untouched. Everything runs as DataFrame expressions on whole texts, without a shuffle of texts.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import BLANKS, NOT_BLANK, stored

SYMBOLS = "#*$%&|<>"
MIN_WORDS = 50
REPEAT_PERCENT = 50
#: Function words of the four languages (fixed values).
FUNCTION_WORDS = (
    "the", "of", "and", "to", "in", "a", "is", "that", "for", "it", "was", "with", "on", "be", "by", "this",
    "der", "die", "und", "den", "von", "zu", "das", "mit", "sich", "des", "auf", "ist", "im", "dem", "nicht",
    "de", "la", "le", "et", "les", "un", "une", "que", "du", "dans", "en", "pour", "qui", "par", "el", "los",
    "se", "del", "las", "al", "con", "para", "su", "una", "es", "des", "au",
)
RULES = ("symbols", "capitals", "exclaims", "word_length", "repeats", "dup_lines", "function_words", "length")


def with_counts(df: DataFrame, text: str = "text", prefix: str = "") -> DataFrame:
    """Add the counts that the rules use, each a long named ``prefix`` + name."""
    p, w, h, s, c = (f"__q_{x}" for x in "pwhsc")
    kept = df.columns
    df = df.withColumn(p, F.coalesce(F.col(text), F.lit("")))
    df = df.withColumn(w, F.array_remove(F.split(F.col(p), BLANKS), ""))
    n = F.size(w)
    # Hashes of the three-word windows; a window that occurs twice covers its three words.
    df = df.withColumn(
        h,
        F.when(
            n >= 3,
            F.transform(
                F.sequence(F.lit(0), n - 3), lambda i: F.xxhash64(F.get(w, i), F.get(w, i + 1), F.get(w, i + 2))
            ),
        ),
    )
    df = df.withColumn(
        s,
        F.when(
            F.size(F.array_distinct(h)) < F.size(h),
            F.sort_array(F.transform(F.col(h), lambda x, i: F.struct(x.alias("h"), i.alias("p")))),
        ),
    )
    last = F.size(s) - 1
    hash_at = lambda i: F.get(F.col(s), i)["h"]
    df = df.withColumn(
        c,
        F.when(
            F.col(s).isNotNull(),
            F.sort_array(
                F.transform(
                    F.filter(
                        F.sequence(F.lit(0), last),
                        lambda i: hash_at(i).eqNullSafe(hash_at(i - 1)) | hash_at(i).eqNullSafe(hash_at(i + 1)),
                    ),
                    lambda i: F.get(F.col(s), i)["p"],
                )
            ),
        ),
    )
    repeated = F.when(
        F.col(c).isNotNull(),
        F.aggregate(
            F.sequence(F.lit(0), F.size(c) - 1),
            F.lit(0),
            lambda a, i: a + F.least(F.lit(3), F.coalesce(F.get(F.col(c), i + 1) - F.get(F.col(c), i), F.lit(3))),
        ),
    ).otherwise(0)
    lines = F.filter(F.split(F.col(p), "\n"), lambda x: x.rlike(NOT_BLANK))
    listed = lambda x: F.lower(x).isin(*FUNCTION_WORDS)
    counts = {
        "n_words": n,
        "word_chars": F.length(F.translate(p, " \t\n\x0b\f\r", "")),
        "n_symbols": F.length(p) - F.length(F.translate(p, SYMBOLS, "")),
        "n_dup_lines": F.size("__q_lines") - F.size(F.array_distinct("__q_lines")),
        "n_repeat_words": repeated,
        "n_lines": F.size("__q_lines"),
        "n_capitals": F.size(F.filter(w, lambda x: (F.length(x) > 2) & (F.upper(x) == x) & (F.lower(x) != x))),
        "n_exclaims": F.length(p) - F.length(F.replace(F.col(p), F.lit("!"), F.lit(""))),
        "n_function_words": F.size(F.filter(w, listed)),
    }
    # Generating one row from one keeps the counts as columns: filters on them aren't pushed below
    # and so don't compute the counts again for every mention.
    row = F.struct(*[x.cast("long").alias(f"{prefix}{k}") for k, x in counts.items()])
    df = df.withColumn("__q_lines", lines).select(*kept, F.explode(F.array(row)).alias("__q_row"))
    return df.select(*kept, "__q_row.*")


def votes(prefix: str = "") -> dict[str, Column]:
    """One column for each rule: 1 good, -1 bad, 0 abstains."""
    x = lambda name: F.col(f"{prefix}{name}").cast("double")
    words, lines = F.greatest(x("n_words"), F.lit(1.0)), F.greatest(x("n_lines"), F.lit(1.0))

    def rule(bad: Column, good: Column) -> Column:
        return F.when(bad, -1).when(good, 1).otherwise(0)

    mean = x("word_chars") / words
    return {
        "symbols": rule(x("n_symbols") > 0.15 * words, x("n_symbols") <= 0.03 * words),
        "capitals": rule(x("n_capitals") > 0.3 * words, x("n_capitals") <= 0.05 * words),
        "exclaims": rule(x("n_exclaims") > 0.3 * words, x("n_exclaims") <= 0.05 * words),
        "word_length": rule((mean < 2.5) | (mean > 11), (mean >= 3.5) & (mean <= 8)),
        "repeats": rule(x("n_repeat_words") > 0.3 * words, x("n_repeat_words") <= 0.1 * words),
        "dup_lines": rule(x("n_dup_lines") > 0.3 * lines, x("n_dup_lines") <= 0.05 * lines),
        "function_words": rule(x("n_function_words") < 0.02 * words, x("n_function_words") >= 0.08 * words),
        "length": rule(x("n_words") < MIN_WORDS, x("n_words") >= 3 * MIN_WORDS),
    }


def base_failed(prefix: str = "") -> Column:
    n = F.col(f"{prefix}n_words")
    return (n < MIN_WORDS) | (100 * F.col(f"{prefix}n_repeat_words") > REPEAT_PERCENT * n)


def fit(patterns: list[tuple[tuple[int, ...], int]], rounds: int = 60) -> tuple[float, list[dict[int, float]]]:
    """Expectation-maximisation on counted vote patterns.

    Returns the log odds of the prior and, for each rule, the log likelihood ratio of each vote. Abstaining
    says nothing. Rules start out as rarely wrong about good documents and often blind to bad ones (a bad
    document is mostly bad in one way), and a good vote never counts against a document nor a bad one for it.
    """
    rules = len(RULES)
    total = sum(n for _, n in patterns)
    prior = 0.8
    good = [{1: 0.97, -1: 0.03} for _ in range(rules)]
    bad = [{1: 0.70, -1: 0.30} for _ in range(rules)]

    def ratios() -> list[dict[int, float]]:
        return [
            {1: max(0.0, math.log(g[1] / b[1])), 0: 0.0, -1: min(0.0, math.log(g[-1] / b[-1]))} for g, b in zip(good, bad, strict=True)
        ]

    for _ in range(rounds if total else 0):
        g = [{1: 9.7, -1: 0.3} for _ in range(rules)]
        b = [{1: 0.7, -1: 0.3} for _ in range(rules)]
        mass, ratio, start = 1.0, ratios(), math.log(prior / (1 - prior))
        for vote, n in patterns:
            odds = start + sum(r[v] for r, v in zip(ratio, vote, strict=True))
            p = 1 / (1 + math.exp(-max(-40.0, min(40.0, odds))))
            mass += n * p
            for j, v in enumerate(vote):
                if v:
                    g[j][v] += n * p
                    b[j][v] += n * (1 - p)
        prior = min(0.99, max(0.5, mass / (total + 2)))
        good = [{v: x / sum(d.values()) for v, x in d.items()} for d in g]
        bad = [{v: x / sum(d.values()) for v, x in d.items()} for d in b]
    return math.log(prior / (1 - prior)), ratios()


def vote_patterns(counted: DataFrame, prefix: str = "") -> list[tuple[tuple[int, ...], int]]:
    """Counts of vote patterns over all rows: at most 3 ** len(RULES) rows reach the driver."""
    rows = counted.select(*[c.alias(k) for k, c in votes(prefix).items()]).groupBy(*RULES).count().collect()
    return sorted((tuple(r[k] for k in RULES), r["count"]) for r in rows)


def posterior(model: tuple[float, list[dict[int, float]]], prefix: str = "") -> Column:
    prior, ratio = model
    cast, odds = votes(prefix), F.lit(float(prior))
    for k, r in zip(RULES, ratio, strict=True):
        odds = odds + F.when(cast[k] == 1, r[1]).when(cast[k] == -1, r[-1]).otherwise(r[0])
    return 1 / (1 + F.exp(-odds))


def score(df: DataFrame, id_col: str = "doc_id", text: str = "text", threshold: float = 0.5) -> DataFrame:
    """One row per input row: id, counts, base_failed, posterior, kept."""
    counted = stored(with_counts(df.select(F.col(id_col), F.col(text)), text).drop(text), "quality")
    model = fit(vote_patterns(counted))
    out = counted.withColumns({"base_failed": base_failed(), "quality": posterior(model)})
    return out.withColumn("kept", ~F.col("base_failed") & (F.col("quality") >= threshold))


def keep_good(df: DataFrame, text: str = "text", threshold: float = 0.5) -> DataFrame:
    """The rows of ``df`` that are kept, with their own columns. Two scans, no shuffle of texts."""
    model = fit(vote_patterns(with_counts(df.select(text), text, "__q1_"), "__q1_"))
    counted = with_counts(df, text, "__q1_")
    good = counted.where(~base_failed("__q1_") & (posterior(model, "__q1_") >= threshold))
    return good.select(*df.columns)
