"""Secret scan with multipart credential linking, as row-local DataFrame expressions.

Base kinds are found everywhere. Weak parts (a bare long key, a service endpoint) say little alone;
they are reported only where complementary parts stand within the same scope: a weak key needs an
access identifier within ``SCOPE`` code points, and an endpoint needs an access identifier and a secret.
The interval join of parts is made inside each text, by one pass over its sorted positions, so no text
and no part is shuffled, and a hot source makes no hot task. A text of n matches takes n * sqrt(n) short copies.

Spans are given in code points, end exclusive, of the whole text. Null texts count as empty; rows are
judged one by one, so ties, repeated rows and extra columns change nothing; an empty table gives
an empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

KINDS = ("assign", "access", "hex", "linked_key", "linked_endpoint")
#: Base patterns (fixed values) and the least length of what they must hold.
ASSIGN = (
    r"(?:[pP][aA][sS][sS][wW][oO][rR][dD]|[pP][aA][sS][sS][wW][dD]|[sS][eE][cC][rR][eE][tT]|[tT][oO][kK][eE][nN]"
    r"|[aA][pP][iI]_?[kK][eE][yY])[\"']?\x20*[:=]\x20*[\"']?[A-Za-z0-9+/_.=-]+"
)
ASSIGN_VALUE = r"^[A-Za-z_]+[\"']?\x20*[:=]\x20*[\"']?([A-Za-z0-9+/_.=-]+)$"
ACCESS = r"AKIA[A-Z0-9]{16,}"
HEX = r"[0-9a-f]{24,}"
#: Weak parts (fixed values): forty characters of base 64 that stand alone, and addresses of services.
WEAK_KEY = r"(?<![A-Za-z0-9+/=_-])[A-Za-z0-9+/]{40}(?![A-Za-z0-9+/=_-])"
#: The same just after an equals sign, as in ``key=value``.
GIVEN_KEY = r"(?<==)[A-Za-z0-9+/]{40}(?![A-Za-z0-9+/=_-])"
ENDPOINT = r"\b(?:https?|s3|ftp|postgres|mysql|redis|amqp)://[^\x20\x09-\x0D\"'<>]+"
SCOPE = 200


def fixed(df: DataFrame, keep: list[str], **made: Column) -> DataFrame:
    """``keep`` and the new columns, computed once a row: functions over arrays that mention them don't compute them again."""
    row = F.struct(*[x.alias(k) for k, x in made.items()])
    return df.select(*keep, F.explode(F.array(row)).alias("__s_row")).select(*keep, "__s_row.*")


def scanned(items: Column, value, join, zero: int) -> Column:
    """For each item the values of all before it, joined (by sum or maximum), as an array of longs.

    In blocks of about the root of their number: block totals, their running value, then each block from there. An array
    that grows by one is copied each time, so that n items take n * sqrt(n) short copies and not n * n. ``items`` is a column, not an expression.
    """
    n = F.size(items)
    width = F.ceil(F.sqrt(n.cast("double"))).cast("int")
    start = F.lit(zero).cast("long")
    blocks = F.transform(F.sequence(F.lit(0), F.ceil(n / width).cast("int") - 1), lambda k: F.slice(items, k * width + 1, width))

    def running(values: Column, first: Column, of) -> Column:
        state = F.struct(first.alias("at"), F.array().cast("array<long>").alias("out"))
        step = lambda a, x: F.struct(join(a["at"], of(x)).alias("at"), F.concat(a["out"], F.array(a["at"])).alias("out"))
        return F.aggregate(values, state, step, lambda a: a["out"])

    totals = F.transform(blocks, lambda b: F.aggregate(b, start, lambda a, x: join(a, value(x))))
    whole = F.flatten(F.zip_with(blocks, running(totals, start, lambda x: x), lambda b, first: running(b, first, value)))
    return F.when(n > 0, whole).otherwise(F.array().cast("array<long>"))


def matches(text: Column, pattern: str) -> Column:
    """(gap, m): leftmost non-overlapping matches, each with the number of code points between it and the one before."""
    gaps = F.transform(F.split(text, pattern, -1), lambda x: F.length(x).cast("long"))
    found = F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    both = F.zip_with(found, F.slice(gaps, F.lit(1), F.size(found)), lambda m, gap: F.struct(gap.alias("gap"), m.alias("m")))
    return F.when(text.rlike(pattern), both).otherwise(F.array().cast("array<struct<gap:long,m:string>>"))


def spans_of(found: Column, kind: int, keep=None) -> Column:
    """(start, end, kind) of a column of matches: running sums of gaps and lengths. ``keep`` filters on the matched string."""
    before = scanned(found, lambda x: x["gap"] + F.length(x["m"]), lambda a, x: a + x, 0)
    spans = F.zip_with(
        found, before, lambda x, at: F.struct((at + x["gap"]).alias("start"), (at + x["gap"] + F.length(x["m"])).alias("end"), F.lit(kind).alias("kind"), x["m"].alias("m"))
    )
    good = F.filter(spans, lambda s: keep(s["m"])) if keep else spans
    return F.transform(good, lambda s: F.struct(s["start"].alias("start"), s["end"].alias("end"), s["kind"].alias("kind")))


def joined(spans: Column) -> Column:
    """kind:start:end by start, then kind in listed order."""
    name = F.array(*[F.lit(k) for k in KINDS])
    return F.array_join(
        F.transform(
            F.sort_array(F.transform(spans, lambda s: F.struct(s["start"].alias("start"), s["kind"].alias("kind"), s["end"].alias("end")))),
            lambda s: F.concat_ws(":", F.get(name, s["kind"] % 10), s["start"].cast("string"), s["end"].cast("string")),
        ),
        ",",
    )


def meeting(df: DataFrame, ones: str, others: Column, scope: int, out: str, negate: bool = False) -> DataFrame:
    """Adds ``out``: the spans of ``ones`` that some of ``others`` comes nearer to than ``scope``, or with ``negate``, that none does.

    An interval join by one sorted pass: a span is met if, of the others that start before its end and the scope, the
    farthest end passes its start less the scope.
    """
    keep = [c for c in df.columns if c != out]
    event = lambda key, is_one, s: F.struct(key.alias("key"), F.lit(is_one).alias("t"), s["start"].alias("start"), s["end"].alias("end"), s["kind"].alias("kind"))
    asked = F.transform(F.col(ones), lambda s: event(s["end"] + scope, 0, s))
    # Where nothing is asked, nothing is sorted.
    events = F.when(F.size(ones) > 0, F.sort_array(F.concat(asked, F.transform(others, lambda s: event(s["start"], 1, s))))).otherwise(F.slice(asked, 1, 0))
    df = fixed(df, keep, __s_events=events)
    reach = scanned(F.col("__s_events"), lambda e: F.when(e["t"] == 1, e["end"]).otherwise(F.lit(-(1 << 40))), lambda a, x: F.greatest(a, x), -(1 << 40))
    judged = F.zip_with(F.col("__s_events"), reach, lambda e, far: F.struct(e.alias("e"), (e["start"] < far + scope).alias("met")))
    hit = F.filter(judged, lambda x: (x["e"]["t"] == 0) & (~x["met"] if negate else x["met"]))
    spans = F.transform(hit, lambda x: F.struct(x["e"]["start"].alias("start"), x["e"]["end"].alias("end"), x["e"]["kind"].alias("kind")))
    return fixed(df, keep, **{out: spans})


def scan(df: DataFrame, id_col: str = "doc_id", text: str = "text", scope: int = SCOPE) -> DataFrame:
    """One row per input row: id, the spans of each kind, and their digest columns."""
    t, c = F.col("__s_t"), F.col
    # Under a name of its own, which no other column's clashes with.
    d = df.select(c(id_col).alias("__s_id"), F.coalesce(c(text), F.lit("")).alias("__s_t"))
    value = lambda m: F.length(F.regexp_extract(m, ASSIGN_VALUE, 1)) >= 6
    # Weak parts count only beside an access identifier, so other texts aren't searched for them.
    beside = lambda pattern: F.when(t.rlike(ACCESS), matches(t, pattern)).otherwise(F.array().cast("array<struct<gap:long,m:string>>"))
    d = fixed(d, ["__s_id"], assign=matches(t, ASSIGN), access=matches(t, ACCESS), hex=matches(t, HEX), weak=beside(WEAK_KEY), given=beside(GIVEN_KEY), ends=beside(ENDPOINT))
    # A given key has a kind of its own on the way, ten above that of weak ones.
    d = fixed(
        d, ["__s_id"],
        assign=spans_of(c("assign"), 0, value), access=spans_of(c("access"), 1), hex=spans_of(c("hex"), 2),
        keys=F.concat(spans_of(c("weak"), 3), spans_of(c("given"), 13)), ends=spans_of(c("ends"), 4),
    )
    base = F.concat("assign", "access", "hex")
    d = meeting(d, "keys", base, 0, "keys", negate=True)
    d = meeting(d, "keys", c("access"), scope, "keys")
    # An address may hold a given key, as in its query; both are reported.
    d = meeting(d, "ends", F.concat(base, F.filter("keys", lambda s: s["kind"] == 3)), 0, "ends", negate=True)
    d = meeting(d, "ends", c("access"), scope, "ends")
    d = meeting(d, "ends", F.concat("assign", "hex", "keys"), scope, "ends")
    return d.select(
        c("__s_id").alias(id_col),
        F.size("assign").cast("long").alias("n_assign"),
        F.size("access").cast("long").alias("n_access"),
        F.size("hex").cast("long").alias("n_hex"),
        F.sha2(joined(base), 256).alias("base_sha256"),
        joined(F.concat(base, "keys", "ends")).alias("spans"),
        F.size("keys").cast("long").alias("n_linked_key"),
        F.size("ends").cast("long").alias("n_linked_endpoint"),
    )
