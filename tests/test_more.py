import pytest
from pyspark.sql import functions as F

from relseq import corpora, workloads
from relseq.functions import relations, taxonomy
from relseq.operators import baselines, costs, matching, patterns, patternsets, refine, typemining
from relseq.operators import corpus as ops
from relseq.sources import tables
from relseq.streaming import sequences as streams

from conftest import DATA

SMALL = f"{DATA}/sf0.001"


@pytest.fixture(scope="module")
def mined(spark):
    return typemining.mine(corpora.sessions(spark, SMALL), 0.25, 2, max_events=2)


def test_matrix_layouts_agree_with_item_support(mined):
    leafs = refine.numbered(refine.leaf_rows(mined)).persist()
    want = {(r["skeleton"], r["item_id"]): r["support"] for r in refine.vocabulary(leafs).collect()}
    rows = refine.matrix(leafs, "rows").select("skeleton", "seq_id", "occurrence", F.explode("items").alias("i"))
    by_sequence = rows.select("skeleton", "seq_id", "i").distinct().groupBy("skeleton", "i").count()
    assert {(r["skeleton"], r["i"]): r["count"] for r in by_sequence.collect()} == want
    bits = refine.matrix(leafs, "bitmaps").persist()
    set_bits = bits.groupBy("skeleton", "item_id").agg(F.sum(F.bitmap_count("bits")).alias("n"))
    by_occurrence = rows.groupBy("skeleton", "i").count()
    assert {(r["skeleton"], r["item_id"]): r["n"] for r in set_bits.collect()} == {(r["skeleton"], r["i"]): r["count"] for r in by_occurrence.collect()}
    # Joined bit by bit, bitmaps give the support of a vector: both concepts in one occurrence, not in one sequence.
    names = {(r["skeleton"], r["slot"], r["concept"]): r["item_id"] for r in refine.vocabulary(leafs).collect()}
    some = [k for k in refine.refine(mined, "all").where("skeleton = 'A ; A'").collect() if sum(c != "" for c in k["vector"]) == 2][:4]
    assert some
    for r in some:
        asked = [names[("A ; A", i + 1, c)] for i, c in enumerate(r["vector"]) if c]
        assert refine.bitmap_support(bits, leafs, "A ; A", asked) == r["support"]


@pytest.mark.parametrize("gap", [None, 1, 3])
def test_pattern_growth_equals_the_miner(spark, gap):
    c = corpora.sessions(spark, SMALL)
    want = typemining.mine(c, 0.12, gap)
    got = baselines.prefix_growth(c, 0.12, gap)
    assert got == {s: n for s, (n, _) in want.skeletons.items()} and max(len(patterns.parse(s)[0]) for s in got) > 3


def test_a_gap_of_nothing_allows_nothing(spark):
    c = corpora.sessions(spark, SMALL)
    for strategy in ("grow", "sql"):
        assert matching.occurrences(c, ["A ; A", "A A"], 0, strategy=strategy).count() == 0
        assert matching.occurrences(c, ["A ; A"], None, 0, strategy=strategy).count() == 0


@pytest.mark.parametrize("rows", [50, 700])
def test_partitioned_refinement_in_many_chunks(spark, mined, monkeypatch, rows):
    want = {(r["skeleton"], tuple(r["vector"])): r["support"] for r in refine.refine(mined, "all").collect()}
    monkeypatch.setattr(refine, "CHUNK_ROWS", rows)
    monkeypatch.setattr(refine, "VECTOR_BLOCK", 100)
    got = {(r["skeleton"], tuple(r["vector"])): r["support"] for r in refine.refine(mined, "all", "partitioned").collect()}
    assert got == want


def test_sets_of_patterns(spark):
    a = spark.createDataFrame([("s", ["x"], 3), ("s", ["y"], 4), ("t", ["x"], 5), ("s", ["w"], 2)], "skeleton string, vector array<string>, support long")
    b = spark.createDataFrame([("s", ["x"], 3), ("s", ["y"], 6), ("s", ["z"], 1), ("s", ["w"], 1)], "skeleton string, vector array<string>, support long")
    kinds = {(r["skeleton"], r["vector"][0]): r["change"] for r in patternsets.changes(a, b).collect()}
    assert kinds == {("s", "x"): "same", ("s", "y"): "more", ("t", "x"): "gone", ("s", "z"): "new", ("s", "w"): "less"}
    assert patternsets.union(a, b).count() == 5 and patternsets.intersection(a, b).count() == 3 and patternsets.difference(a, b).count() == 1
    assert {r["support"] for r in patternsets.union(a, b).where("vector[0] = 'y'").collect()} == {6}


def test_partial_matches_across_batches(spark, tmp_path):
    """Matches that begin in one file and end in a later one, and none beyond the span."""
    at = "timestamp'2024-01-01 00:00:00' + make_interval(0, 0, 0, 0, 0, 0, s)"
    rows = [(1, 1, "F", 0), (1, 2, "A", 50), (2, 3, "F", 10), (1, 4, "F", 90), (1, 5, "A", 100), (2, 6, "A", 111), (1, 7, "A", 190)]
    schema = "user_id long, event_id long, type string, s long"
    for n, part in enumerate((rows[:3], rows[3:5], rows[5:])):
        spark.createDataFrame(part, schema).selectExpr("user_id", "event_id", "type", f"{at} at").coalesce(1).write.parquet(str(tmp_path / "in" / f"part={n}"))
    live = spark.readStream.schema("user_id long, event_id long, type string, at timestamp, part int").option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    found = streams.partial_matches(live.withWatermark("at", "10 minutes").select("user_id", "event_id", "type", "at"), [["F", "A"], ["F", "F", "A"]], 100)
    query = found.writeStream.format("memory").queryName("matches").option("checkpointLocation", str(tmp_path / "state")).trigger(availableNow=True).start()
    query.awaitTermination()
    got = sorted((r["user_id"], r["skeleton"], tuple(r["event_ids"])) for r in spark.table("matches").collect())
    assert got == [(1, "F ; A", (1, 2)), (1, "F ; A", (1, 5)), (1, "F ; A", (4, 5)), (1, "F ; A", (4, 7)), (1, "F ; F ; A", (1, 4, 5))]
    assert streams.late_rows(query) == 0


def test_late_rows_are_counted(spark, tmp_path):
    for n, seconds in enumerate(([5, 4000], [9000], [1, 2, 9100])):
        rows = [(1, 10 * n + i, s) for i, s in enumerate(seconds)]
        spark.createDataFrame(rows, "user_id long, event_id long, s long").selectExpr("user_id", "event_id", "timestamp'2024-01-01 00:00:00' + make_interval(0, 0, 0, 0, 0, 0, s) ts").coalesce(1).write.parquet(str(tmp_path / "in" / f"part={n}"))
    live = spark.readStream.schema("user_id long, event_id long, ts timestamp, part int").option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    counted = streams.with_time(live, "ts", "10 minutes").groupBy(F.window("at", "10 minutes")).count()
    query = counted.writeStream.format("memory").queryName("late").outputMode("append").option("checkpointLocation", str(tmp_path / "state")).trigger(availableNow=True).start()
    query.awaitTermination()
    assert streams.late_rows(query) >= 1


def test_stage_shapes_and_the_archive(spark, tmp_path):
    import zipfile
    from pathlib import Path

    from relseq import session

    timed = spark.createDataFrame([("gap", "full", 1.0, 3.0, 4.0), ("gap", "full", 2.0, 1.0, 3.0)], "workload string, scenario string, t_stage1 double, t_stage2 double, t_total double")
    assert [tuple(r) for r in workloads.stage_shapes(timed).collect()] == [("gap", "full", 2, 1, round(4 / 7, 4))]
    names = zipfile.ZipFile(session.archive(Path(session.__file__).resolve().parent.parent)).namelist()
    assert "relseq/operators/refine.py" in names


def test_library_miner_counts_rows(mined):
    leafs = refine.leaf_rows(mined)
    found = {tuple(r["items"]): r["freq"] for r in baselines.fpgrowth_items(leafs, "A ; A", 0.3).collect()}
    rows = {f"{r['slot']}:{r['concept']}": r["row_support"] for r in baselines.row_support(leafs).where("skeleton = 'A ; A'").collect()}
    single = {k[0]: v for k, v in found.items() if len(k) == 1}
    assert single and all(rows[k] == v for k, v in single.items())


def test_extended_sequences_hold_all_ancestors(spark):
    c = corpora.sessions(spark, SMALL)
    got = baselines.extended_sequences(c).select(F.aggregate("sequence", F.lit(0), lambda n, s: n + F.size(s)).alias("n")).agg(F.sum("n")).first()[0]
    assert got > ops.unpack(c).count()


def test_windows_close_the_same_sequences(spark):
    events = tables.read_table(spark, SMALL, "events").where("props is not null")
    long = corpora.event_days(events, 3).join(events.select("event_id", "user_id", "ts"), "event_id")
    closed = streams.close_sequences(streams.with_time(long, "ts"))
    c = corpora.sessions(spark, SMALL)
    assert closed.count() == c.size()
    again = streams.packed(closed, ["A", "F"])
    assert sorted(r["n_events"] for r in again.collect()) == sorted(r["n_events"] for r in c.sequences.collect())
    assert streams.close_sequences(streams.with_time(long, "ts"), "3 days", "0 days", "1 day").count() > c.size()
    gaps = streams.sessions(streams.with_time(long, "ts"), "1 day")
    assert gaps.select(F.sum(F.size("xs"))).first()[0] == long.count()


def test_stream_drops_replays(spark, tmp_path):
    events = tables.read_table(spark, SMALL, "events")
    path = str(tmp_path / "in")
    events.limit(50).union(events.limit(50)).write.parquet(path)
    live = streams.without_replays(streams.with_time(spark.readStream.schema(events.schema).parquet(path), "ts", "400 days"))
    live.writeStream.format("memory").queryName("once").option("checkpointLocation", str(tmp_path / "state")).trigger(availableNow=True).start().awaitTermination()
    assert spark.table("once").count() == 50


@pytest.mark.parametrize("name", ["weeks", "dialogues", "sources", "vectors", "web"])
def test_other_corpora_are_mined(spark, name):
    m = typemining.mine(getattr(corpora, name)(spark, SMALL), 0.3, 2, max_events=2)
    found = refine.to_patterns(m, refine.refine(m))
    assert m.skeletons and found.where("support < 1 or pattern is null").count() == 0


def test_resolvers(spark):
    row = spark.createDataFrame([((5, "abc", [1.0, 0.0]), (9, "b", [0.8, 0.6]))], "a struct<day:int,text:string,v:array<double>>, b struct<day:int,text:string,v:array<double>>")
    a, b = F.struct(F.col("a").alias("attrs")), F.struct(F.col("b").alias("attrs"))
    asked = [relations.time_lag([2, 7])[1], relations.cosine("v", 0.9, 0.5)[1], relations.contains("text")[1], relations.compare("day")[1], relations.identity("day")[1]]
    assert list(row.select(*[r(a, b) for r in asked]).first()) == ["within7", "Similar/Some", "Contains", "Higher", "≠"]
    with pytest.raises(ValueError):
        relations.Relation("F", "A", *relations.identity("day"))


def test_deepest_and_common(spark):
    df = spark.createDataFrame([(["a", "a/b/c", "a/b"], "a/b/c", "a/b/d"), ([], "x", "y")], "cs array<string>, u string, v string")
    got = df.select(taxonomy.deepest(F.col("cs")), taxonomy.common_ancestor(F.col("u"), F.col("v"))).collect()
    assert [tuple(r) for r in got] == [("a/b/c", "a/b"), ("", "")]


def test_grid_cell_and_patterns_sink(spark, mined, tmp_path):
    cell = costs.run_cell(corpora.sessions(spark, SMALL), costs.Cell("x", "full", 0.3, max_gap=2, max_events=2))
    assert cell.patterns > 0 and cell.stage1 > 0 and cell.occurrences >= cell.skeletons
    found = refine.to_patterns(mined, refine.refine(mined))
    for kind in ("json", "csv", "parquet"):
        tables.write_patterns(found, str(tmp_path / kind), kind)
        assert spark.read.format(kind).option("header", True).load(str(tmp_path / kind)).count() == found.count()


def test_entry(spark):
    assert workloads.flagship(spark, SMALL).count() > 0


def test_memory_is_reported(spark):
    spark.range(1000).groupBy((F.col("id") % 7).alias("k")).count().collect()
    got = costs.peak_memory(spark)
    assert got["driver"]["max_memory"] > 0 and got["driver"]["shuffle_write"] > 0
