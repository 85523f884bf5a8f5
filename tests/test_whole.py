"""Jobs that must be done whole: no cap on length, no subset of the input, no switch that changes results."""

import duckdb
import pytest

import __spark_entry__ as entry
from relseq import corpora, oracles, workloads
from relseq.functions import taxonomy
from relseq.operators import costs, refine, typemining

from conftest import DATA
from test_mining import SMALL, asked, rows


@pytest.fixture(scope="module")
def db():
    c = duckdb.connect()
    for t in ("events", "lineitem", "part"):
        c.execute(f"create view {t} as select * from '{SMALL}/{t}.parquet'")
    return c


# -- skeletons of any length ------------------------------------------------------------------------------------


def test_the_search_ends_by_itself(spark, db):
    c = corpora.sessions(spark, SMALL)
    m = typemining.mine(c, 0.10, 3)
    want = asked(db, oracles.skeletons(0.10, 3, 8))
    assert m.complete and rows(m.table()) == want
    assert max(n for n in m.table().toPandas()["n_events"]) == 7
    capped = typemining.mine(c, 0.10, 3, max_events=3)
    assert not capped.complete and set(capped.skeletons) < set(m.skeletons)
    assert typemining.mine(c, 0.10, 3, max_events=8).complete


def test_flagship_has_no_length_limit(spark):
    assert workloads.flagship(spark, SMALL).where("n_events > 4").count() > 0
    assert costs.Cell("x", "full", 0.1).max_events is None and all(c.max_events is None for c in workloads.gap_sweep_cells(0.1, "full"))


# -- refinement above the size of a task ------------------------------------------------------------------------


def test_generic_refinement_above_the_group_limit(spark, monkeypatch):
    d = f"{DATA}/sf0.01"
    c = duckdb.connect()
    for t in ("lineitem", "part"):
        c.execute(f"create view {t} as select * from '{d}/{t}.parquet'")
    monkeypatch.setattr(refine, "GROUP_LIMIT", 100)
    monkeypatch.setattr(refine, "CHUNK_ROWS", 12_000)
    spark.conf.set("spark.sql.adaptive.enabled", "false")  # or so small a table is put into one partition
    try:
        got = rows(entry.queries()["generic_refinement"](spark, d))
    finally:
        spark.conf.unset("spark.sql.adaptive.enabled")
    assert got == asked(c, oracles.oracle_sql()["generic_refinement"])


def test_partitioned_counts_scattered_sequences_once(spark, monkeypatch):
    monkeypatch.setattr(refine, "CHUNK_ROWS", 4)
    data = [("s", str(i % 10), [x]) for x in ("a/b", "a/c", "d") for i in range(10 if x != "d" else 4)]
    leafs = spark.createDataFrame(data, "skeleton string, seq_id string, leaf array<string>").repartition(5)
    got = {(tuple(r["vector"]), r["support"]) for r in refine.refine_any(leafs, 5, "all", "partitioned").collect()}
    assert got == {(("",), 10), (("a",), 10), (("a/b",), 10), (("a/c",), 10)}


# -- neighbours in a graph of concepts --------------------------------------------------------------------------


@pytest.mark.parametrize("width", [7, 10_000])
def test_dag_common_ancestor_takes_every_part(spark, db, monkeypatch, width):
    monkeypatch.setattr(workloads, "KEY_RANGE", width)
    got = workloads.dag_common_ancestor(spark, SMALL)
    assert rows(got) == asked(db, oracles.oracle_sql()["dag_common_ancestor"])
    part = {f"part {r['p_partkey']}": (r["p_type"], r["p_brand"]) for r in spark.read.parquet(f"{SMALL}/part.parquet").collect()}
    assert got.count() == len(part) - 1
    dag = taxonomy.Dag.of([e for p, own in part.items() for c in own for e in ((p, c), (c, "Any"))])
    for r in got.collect():
        shared = dag.above(r["a"]) & dag.above(r["b"])
        assert r["common"] == dag.common_ancestor({r["a"], r["b"]}) and r["conjunction"] == " & ".join(sorted(dag.most_specific(shared)))
