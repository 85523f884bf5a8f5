from pyspark.sql import functions as F

from relseq import corpora, sql
from relseq.functions import joins
from relseq.operators import matching, patterns, refine, typemining

from conftest import DATA

SMALL = f"{DATA}/sf0.001"


def test_as_of_takes_the_latest_row_even_if_its_value_is_null(spark):
    left = spark.createDataFrame([(1, 5, "x"), (1, 1, "y"), (2, 3, "z")], "k int, t int, name string")
    right = spark.createDataFrame([(1, 2, "a"), (1, 5, None), (2, 9, "b")], "k int, t int, v string")
    got = {r["name"]: (r["last_v"], r["last_t"]) for r in joins.as_of(left, right, ["k"], "t", "t", ["v"]).collect()}
    assert got == {"x": (None, 5), "y": (None, None), "z": (None, None)}


def test_within_equals_the_band_join(spark):
    e = spark.range(200).select((F.col("id") % 7).alias("k"), (F.col("id") * 37 % 101).alias("t"))
    want = e.alias("a").join(e.alias("b"), F.expr("a.k = b.k and b.t > a.t and b.t <= a.t + 9")).count()
    assert joins.within(e, e, ["k"], "t", "t", 9).count() == want


def test_sql_functions(spark):
    sql.register(spark)
    c = corpora.sessions(spark, SMALL)
    c.sequences.select("seq_id", F.transform("events", lambda e: e["type"]).alias("types"), F.transform("events", lambda e: e["txn"]).alias("txns")).createOrReplaceTempView("seq")
    n = spark.sql("select count(*) from seq s, lateral occurrences(s.types, s.txns, 'A ; F', 3, null) o").first()[0]
    assert n == matching.occurrences(c, ["A ; F"], 3).count()
    assert [r[0] for r in spark.sql("select ancestor from ancestors('a/b/c')").collect()] == ["a/b/c", "a/b", "a"]


def test_permuted_orders(spark):
    rows = spark.createDataFrame([(["T", "T", "T", "U"], [1, 1, 1, 1])], "types array<string>, txns array<int>")
    events = F.transform(F.arrays_zip("types", "txns"), lambda z: F.struct(z["types"].alias("type"), z["txns"].alias("txn")))
    made = rows.select(matching.permuted(events, F.array(*[F.lit(i) for i in (1, 2, 3)]), 3).alias("a"), matching.permuted(events, F.array(F.lit(1), F.lit(4)), 3).alias("b")).first()
    assert sorted(made["a"]) == [[1, 2, 3], [1, 3, 2], [2, 1, 3], [2, 3, 1], [3, 1, 2], [3, 2, 1]] and made["b"] == [[1, 4]]
    c = corpora.sessions(spark, SMALL)
    m = typemining.mine(c, 0.2, 2, max_events=2)
    one, more = refine.leaf_rows(m), refine.leaf_rows(m, permute=True)
    assert more.count() > one.count() and one.exceptAll(more).count() == 0


def test_global_maximality(spark):
    m = typemining.mine(corpora.sessions(spark, SMALL), 0.3, None, max_events=2)
    local = {(r["skeleton"], tuple(r["vector"])) for r in refine.refine(m).collect()}
    wide = {(r["skeleton"], tuple(r["vector"])) for r in refine.refine(m, scope="global").collect()}
    assert wide < local
    at_or_above = lambda a, b: all(not x or x == y or y.startswith(x + "/") for x, y in zip(a, b))
    for s, v in local:
        k = len(patterns.parse(s)[0])
        said = k == 1 and any(at_or_above(v, (w[i],)) and patterns.parse(t)[0][i] == s for t, w in local if len(patterns.parse(t)[0]) == 2 for i in (0, 1))
        assert ((s, v) in wide) == (not said)
