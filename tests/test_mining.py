import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from relseq import corpora, oracles, workloads
from relseq.functions import taxonomy
from relseq.operators import corpus as ops
from relseq.operators import costs, matching, patterns, refine, typemining
from relseq.plans import planner
from relseq.sources import tables

from conftest import DATA

SMALL = f"{DATA}/sf0.001"


@pytest.fixture(scope="module")
def sessions(spark):
    return corpora.sessions(spark, SMALL)


@pytest.fixture(scope="module")
def db():
    c = duckdb.connect()
    for t in tables.TABLES:
        c.execute(f"create view {t} as select * from '{SMALL}/{t}.parquet'")
    return c


def rows(df):
    out = df.toPandas()
    out = out[sorted(out.columns)]
    return sorted(map(tuple, out.astype(object).where(out.notna(), None).values.tolist()), key=str)


def asked(c, sql):
    out = c.execute(sql).df()
    out = out[sorted(out.columns)]
    return sorted(map(tuple, out.astype(object).where(out.notna(), None).values.tolist()), key=str)


CHECKED = ["corpus_profile", "canonical_events", "type_view", "relation_profile", "taxonomy_stats", "occurrences_k2", "occurrences_k3_gap2_join", "occurrences_k3_gap2_kernel", "occurrences_units", "skeletons_k3_ms10_mg2", "skeletons_span_sweep", "refine_closed_rel_k3", "refine_maximal_full_k2", "refine_maximal_rel_k3_backtrack", "refine_maximal_rel_k3_levelwise", "refine_maximal_rel_k3_partitioned", "item_vocabulary", "first_occurrence_loss", "gap_subpattern_violations", "stream_equals_batch", "skeletons_dialogues", "rollup_support_by_level"]


@pytest.mark.parametrize("name", CHECKED)
def test_query_equals_brute_force(spark, db, name):
    assert rows(entry.queries()[name](spark, SMALL)) == asked(db, oracles.oracle_sql()[name])


def test_entry_and_oracles_name_queries():
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_strategies_agree(sessions):
    names = ["A ; F", "A A ; F", "F ; A ; A"]
    found = [rows(matching.occurrences(sessions, names, 3, 5, strategy=s)) for s in ("grow", "kernel", "sql")]
    assert found[0] == found[1] == found[2] and found[0]


def test_equal_support_does_not_merge(spark):
    leafs = spark.createDataFrame([("s", "1", ["x", "a"]), ("s", "1", ["x", "b"])], "skeleton string, seq_id string, leaf array<string>")
    assert [refine.support(leafs, v) for v in (["x", ""], ["x", "a"], ["x", "b"])] == [1, 1, 1]
    found = {tuple(r["vector"]) for r in refine.refine_any(leafs, 1, "maximal").collect()}
    assert found == {("x", "a"), ("x", "b")}


@pytest.mark.parametrize("seed", range(4))
def test_searches_agree_on_random_leaves(seed):
    draw = np.random.default_rng(seed)
    names = ["", "a", "a/b", "a/b/c", "a/d", "e"]
    leaf = [[names[i] for i in row] for row in draw.integers(0, len(names), (40, 3))]
    leaves = refine.Leaves(np.sort(draw.integers(0, 12, 40)), leaf)
    theta = 4
    every = refine.frequent_vectors(leaves, theta)

    def lifts(v):
        return [tuple(c.rpartition("/")[0] if j == i else c for j, c in enumerate(v)) for i in range(3) if v[i]]

    broader = {u for v in every for u in lifts(v)}
    best = {v: n for v, n in every.items() if v not in broader}
    assert refine.maximal_itemsets(leaves, theta) == best
    sets = refine.levelwise_itemsets(leaves, theta)
    assert {refine.itemset_vector(k, 3) for k in sets} | {("", "", "")} == set(every)
    brute = 0
    for v in every:
        covered = {int(s) for s, row in zip(leaves.sequences, leaf) if all(not c or x == c or x.startswith(c + "/") for c, x in zip(v, row))}
        brute += len(covered) != every[v]
    assert brute == 0


def test_partitioned_equals_grouped(sessions):
    m = typemining.mine(sessions, 0.2, 2, max_events=2)
    assert rows(refine.refine(m, "closed")) == rows(refine.refine(m, "closed", "partitioned"))


def test_special_cases(sessions):
    m = typemining.mine(ops.scenario(sessions, "plain"), 0.2, 2, max_events=2)
    found = refine.to_patterns(m, refine.refine(m)).collect()
    assert {r["pattern"] for r in found} == set(m.skeletons) and not any(r["specialised"] for r in found)


def test_layout_has_one_length_for_each_skeleton(sessions):
    m = typemining.mine(sessions, 0.2, 2, max_events=3)
    for r in refine.leaf_rows(m).groupBy("skeleton").agg(F.collect_set(F.size("leaf")).alias("n")).collect():
        assert r["n"] == [len(ops.slot_names(list(patterns.parse(r["skeleton"])[0]), m.corpus.trees, m.corpus.relations))]


def test_taxonomy_columns(spark):
    df = spark.createDataFrame([("a/b", "a/b/c"), ("a", "ab"), ("", "x"), ("a/b", "a/b")], "u string, v string")
    assert [r[0] for r in df.select(taxonomy.subsumes(F.col("u"), F.col("v"))).collect()] == [True, False, True, True]
    tree = taxonomy.from_edges(spark.createDataFrame([("b", "r"), ("c", "r"), ("d", "b")], "child string, parent string"))
    assert {r["concept"] for r in tree.collect()} == {"", "r", "r/b", "r/c", "r/b/d"}
    assert taxonomy.validate(spark.createDataFrame([("b", "r"), ("b", "q")], "child string, parent string")).count() == 3
    pre = [r["concept"] for r in taxonomy.order(tree).orderBy("rank").collect()]
    post = [r["concept"] for r in taxonomy.order(tree, "post").orderBy("rank").collect()]
    assert pre == ["", "r", "r/b", "r/b/d", "r/c"] and post == ["r/b/d", "r/b", "r/c", "r", ""]
    assert taxonomy.stats(taxonomy.heap(spark, 4, 103)).first()["nodes"] == 103


def test_sources_round_trip(spark, sessions, tmp_path):
    tables.save_corpus(sessions, str(tmp_path / "c"), 2)
    again = tables.load_corpus(spark, str(tmp_path / "c"), sessions)
    assert again.size() == sessions.size()
    spark.dataSource.register(tables.PrefixTreeSource)
    tree = spark.read.format("prefix_tree").option("text", corpora.CROSS_TREE).load()
    assert tree.count() == 6 and taxonomy.stats(tree).first()["leaves"] == 4
    occ = matching.occurrences(sessions, ["A ; F", "F ; A"], 1)
    tables.write_occurrences(occ, str(tmp_path / "o"))
    assert spark.read.parquet(str(tmp_path / "o")).count() == occ.count()


def test_planner(sessions):
    p = planner.plan(sessions, 0.1, 3)
    assert p.bounds[1] == sessions.sequences.agg(F.sum("n_events")).first()[0] and "grouped" in p.explain()
    with pytest.raises(ValueError):
        planner.plan(sessions, 0.1, budget=10)


def test_missing_values_are_defined(spark):
    schema = "seq_id string, txn_key long, type string, concepts array<string>, attrs struct<name:string>, event_id long"
    events = spark.createDataFrame([("1", 1, "A", None, ("x",), 1), (None, 1, "A", ["a"], ("x",), 2), ("1", 1, None, ["a"], ("x",), 3), ("1", 2, "A", ["a/b"], None, 4)], schema)
    c = ops.build(events, {"A": ["t"]})
    assert c.size() == 1 and c.sequences.first()["n_A"] == 2
    empty = ops.build(events.limit(0), {"A": ["t"]})
    assert typemining.mine(empty, 0.5, max_events=2).skeletons == {}


def test_trends(spark):
    """More gap, more skeletons; higher support, fewer patterns; growth with the number of sequences near linear."""
    c = ops.scenario(corpora.sessions(spark, f"{DATA}/sf0.01"), "relations")
    few = [len(typemining.mine(c, 0.10, g, max_events=3).skeletons) for g in (1, 3, 5)]
    assert few == sorted(few) and few[0] < few[-1]
    low, high = (refine.refine(typemining.mine(c, ms, 3, max_events=3)).count() for ms in (0.10, 0.18))
    assert high < low
    assert abs(costs.growth([1, 2, 4], [3, 6, 12]) - 1) < 1e-9


def test_all_cells_of_the_grid():
    assert len(workloads.all_cells()) == 66
