import duckdb
from brute import words
from pyspark.sql import functions as F

from rarecount.llm import op3_mix as M


def data():
    out = [(i, " ".join(words(20 + i % 7, i)), ["en", "fr", None][i % 3], "src0" if i % 2 else f"src{i % 13}") for i in range(400)]
    return out + [(900, None, "en", "src1"), (901, "", "en", "src1"), (902, "one two", None, None), (903, "x", "en", "strange")]


def test_equals_sql(spark, docs):
    df = docs(data())
    got = sorted(tuple(r) for r in M.mix(df).collect())
    con = duckdb.connect()
    documents = df.toPandas()[["doc_id", "text", "lang", "source"]]  # noqa: F841
    assert got == sorted(con.sql(f"SELECT doc_id, domain, language, source, epoch, n_tokens, taken_tokens FROM ({M.oracle()})").fetchall())
    total = sum(len((t[1] or "").split()) for t in data())
    assert sum(r[6] for r in got) <= total
    assert all(0 < r[6] <= r[5] for r in got)


def test_shortages_go_to_siblings_first(spark):
    rows = [("web", "en", "a", 100), ("web", "en", "b", 1000), ("books", "en", "c", 1000)]
    leaves = spark.createDataFrame(rows, "domain string, language string, source string, tokens long")
    got = {r.source: r.given for r in M.budgets(leaves, per_mille=400, epochs=1, weights={"web": 1, "books": 1}).collect()}
    # 840 in all, half to each domain; a can use 100 of its 210, its sibling takes the rest.
    assert got == {"a": 100, "b": 320, "c": 420}


def test_drawn_repeats_rows_and_keeps_columns(spark, docs):
    df = docs(data())
    out = M.drawn(df)
    assert out.columns == df.columns
    assert out.count() == M.mix(df).count()
    assert M.drawn(docs([])).count() == 0


def test_drawn_keeps_null_ids_and_tells_repeated_ids_apart(spark, docs):
    rows = data() + [(None, " ".join(words(30, 1000 + i)), "en", f"src{i % 3}") for i in range(20)]
    rows += [(i % 40, " ".join(words(25, 2000 + i)), "fr", f"src{i % 5}") for i in range(80)]
    df = docs(rows)
    out, mixed = M.drawn(df), M.mix(df)
    assert out.count() == mixed.count()

    def tally(d, n):
        return sorted(((r.doc_id is None, r.doc_id or 0, r.n), r["count"]) for r in d.groupBy("doc_id", n.alias("n")).count().collect())

    assert any(r.doc_id is None for r in out.collect())
    assert tally(out, F.size(F.split("text", " "))) == tally(mixed, F.col("taken_tokens").cast("int"))


def test_drawn_stops_where_the_budget_of_a_leaf_ends(spark, docs):
    df = docs([(i, "  " + " \n".join(words(20 + i % 7, i)) + "\t", "en", f"src{i % 13}") for i in range(300)])
    mixed = M.mix(df)
    out = M.drawn(df).select("doc_id", "text").collect()
    got = sorted((r.doc_id, len(r.text.split())) for r in out)
    assert got == sorted((r.doc_id, r.taken_tokens) for r in mixed.collect())
    texts = {r.doc_id: r.text for r in df.collect()}
    assert all(texts[r.doc_id].startswith(r.text) for r in out) and any(texts[r.doc_id] != r.text for r in out)
    total = sum(len(t.split()) for t in texts.values())
    assert sum(n for _, n in got) <= total


def test_rows_of_one_id_are_drawn_by_their_text(spark, docs):
    rows = [(1, " ".join(words(300, 1)), "en", "src0"), (1, " ".join(words(2, 2)), "en", "src0"), (2, " ".join(words(10, 3)), "en", "src0")]
    df = docs(rows)
    for mille in (100, 400, 900, 1000):
        got = sorted(len(r.text.split()) for r in M.drawn(df, per_mille=mille).collect())
        assert got == sorted(r.taken_tokens for r in M.mix(df, per_mille=mille).collect())
