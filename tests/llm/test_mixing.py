import duckdb
import pytest
from pyspark.sql import functions as F

from bedvoids.llm import mixing as M

SCHEMA = "doc_id long, text string, source string, size string, at int"


def rows():
    out = [(i, " ".join(["w"] * (1 + i * 7 % 50)), f"s{i % 5}", "x", 1) for i in range(400)]
    out += [(400 + i, "a\tb\nc d", "tiny", "x", 1) for i in range(3)]
    return out + [(500, None, "s1", "x", 1), (501, "", None, "x", 1), (502, "one two", None, "x", 1), (503, " \t ", "empty", "x", 1), (1, "repeated id", "s1", "x", 1)]


def test_against_sql(spark):
    df = spark.createDataFrame(rows(), SCHEMA).repartition(4)
    got = M.mix(df).select("doc_id", "size", "source_size", "target", "taken")
    con = duckdb.connect()
    con.execute("CREATE TABLE documents (doc_id BIGINT, text VARCHAR, source VARCHAR)")
    con.executemany("INSERT INTO documents VALUES (?, ?, ?)", [r[:3] for r in rows()])
    assert sorted(map(tuple, got.collect())) == sorted(con.execute(M.SQL).fetchall())


def test_targets_are_met(spark):
    df = spark.createDataFrame(rows(), SCHEMA)
    got = M.mix(df).collect()
    total = sum(r["size"] for r in got)
    by = {}
    for r in got:
        by.setdefault(r.source, [r.target, r.source_size, 0])[2] += r.taken
        assert r.taken <= 2 * r["size"]
    assert sum(v[0] for v in by.values()) == pytest.approx(1.5 * total)
    for target, size, taken in by.values():
        assert target <= 2 * size and abs(taken - target) <= 50
    again = M.mix(df.repartition(7)).collect()
    key = lambda rs: sorted((r.doc_id, r["size"], r.taken) for r in rs)
    assert key(got) == key(again)
    mixed = M.mixed(df)
    assert mixed.columns == [*df.columns, "mix_copy"]
    assert mixed.count() == sum(r.copies for r in got)


def test_rows_alike_are_taken_as_often_as_the_mix_says(spark):
    schema = "doc_id long, text string, source string, size string, _id int, _copies int, mix_copy int, meta map<string,int>"
    rows = [(1, "one two three", "a", "x", 1, 2, 3, {"k": 1})] * 700 + [(1, "one two three", "a", "x", 9, 2, 3, {"k": i}) for i in range(50)] + [(i, "w " * (i % 9), "b", None, None, 1, 1, None) for i in range(300)] + [(None, None, None, None, None, None, None, None)] * 5
    df = spark.createDataFrame(rows, schema).repartition(3)
    want = {r.source: r.n for r in M.mix(df).groupBy("source").agg(F.sum("copies").alias("n")).where("n > 0").collect()}
    assert {r.source: r["count"] for r in M.mixed(df).groupBy("source").count().collect()} == want
    assert M.mixed(df).columns == [*df.columns, "mix_copy_"]


def test_empty(spark):
    empty = spark.createDataFrame([], SCHEMA)
    assert M.mix(empty).count() == 0 and M.mixed(empty).count() == 0
    none = spark.createDataFrame([(1, None, "a", "x", 1)], SCHEMA)
    assert [(r["size"], r.target, r.taken) for r in M.mix(none).collect()] == [(0, 0.0, 0)]
