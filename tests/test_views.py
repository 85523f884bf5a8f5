"""Stage 1 over views, and refinement of condensed sequences."""

from itertools import combinations

from pyspark.sql import functions as F

from relseq import corpora
from relseq.operators import corpus as ops
from relseq.operators import matching, refine, typemining

D = "/root/testdata/sf0.001"


def test_mining_stores_no_occurrences(spark):
    before = spark.sparkContext._jsc.getPersistentRDDs().size()
    mined = typemining.mine(corpora.sessions(spark, D), 0.10, 3)
    assert spark.sparkContext._jsc.getPersistentRDDs().size() == before
    told = mined.occurrences().groupBy("skeleton").agg(F.count_distinct("seq_id").alias("s"), F.count("*").alias("o")).collect()
    assert {r["skeleton"]: (r["s"], r["o"]) for r in told} == mined.skeletons


def test_tally_equals_enumeration():
    types, txns, at = list("AFAAFA"), [1, 1, 2, 3, 3, 4], [1, 2, 3, 4, 5, 6]
    name = lambda c: types[c[0]] + "".join((" ; " if txns[j] > txns[i] else " ") + types[j] for i, j in zip(c, c[1:]))
    for gap, span in ((None, None), (2, None), (None, 3), (2, 4)):
        fits = lambda c: all(gap is None or j - i <= gap for i, j in zip(c, c[1:])) and (span is None or c[-1] - c[0] <= span)
        found = [[name(c) for c in combinations(range(6), k) if fits(c)] for k in (1, 2, 3)]
        got = typemining.tally(types, txns, at, [frozenset(x) for x in found], gap, span, True)
        assert got == {s: found[2].count(s) for s in set(found[2])}


def test_span_sweep_reads_its_corpus_as_views(spark):
    plain = ops.scenario(corpora.weeks(spark, D), "plain")
    small = ops.condensed(plain)
    assert small.size() == plain.size() and small.sequences.count() <= plain.sequences.count()
    assert typemining.mine(small, 0.10, None, 10, 3).skeletons == typemining.mine(plain, 0.10, None, 10, 3).skeletons


def test_weighted_refinement_equals_one_row_a_sequence(spark):
    mined = typemining.mine(ops.scenario(corpora.sessions(spark, D), "relations"), 0.10, 3, None, 3)
    each = refine.refine_any(refine.leaf_rows(mined), mined.threshold, "all")
    leafs = refine.leaf_rows(typemining.mine(ops.condensed(mined.corpus), 0.10, 3, None, 3))
    assert leafs.count() < refine.leaf_rows(mined).count()  # fewer rows, each with a number
    shown = lambda df: {(r["skeleton"], tuple(r["vector"]), r["support"]) for r in df.collect()}
    assert shown(each) == shown(refine.refine(mined, "all")) == shown(refine.refine_any(leafs, mined.threshold, "all", "partitioned"))


def test_units_agree_with_growing(spark):
    c = corpora.sessions(spark, D)
    for unit in matching.UNITS:
        mined = typemining.mine(c, 0.10, 2, 4, 2, unit=unit)
        told = {r["skeleton"]: r["count"] for r in mined.occurrences().groupBy("skeleton").count().collect()}
        assert told == {s: n for s, (_, n) in mined.skeletons.items()}


def few_events(spark, tmp_path):
    spark.read.parquet(f"{D}/events.parquet").where("user_id = 1").orderBy("event_id").limit(9).write.parquet(f"{tmp_path}/events.parquet")
    return str(tmp_path)


def test_heap_reads_events(spark, tmp_path):
    from relseq import workloads

    d = few_events(spark, tmp_path)
    keys = {int(r[0]) + 4 for r in spark.read.parquet(f"{d}/events.parquet").select(F.get_json_object("props", "$.k")).collect()}
    nodes = {n >> s for n in keys for s in range(n.bit_length())}
    assert workloads.taxonomy_heap(spark, d).first()["nodes"] == len(nodes)


def test_bounds_are_for_lengths_in_events(spark, tmp_path):
    from relseq import workloads

    d = few_events(spark, tmp_path)
    lengths = {r[0] for r in corpora.sessions(spark, d).sequences.select("n_events").collect()}
    assert {r["n"] for r in workloads.complexity_bounds(spark, d).collect()} == {n for n in lengths if 3 <= n <= 8}


def test_grid_packs_its_corpus_once(spark, monkeypatch):
    from relseq import workloads

    made = []
    condensed = ops.condensed
    monkeypatch.setattr(ops, "condensed", lambda c, *x: made.append(1) or condensed(c, *x))
    cells = [workloads.Cell("gap", "relations", 0.3, max_gap=g, max_events=2) for g in (1, 2)]
    assert workloads.run_grid(spark, D, cells).count() == 2
    assert len(made) == 1
