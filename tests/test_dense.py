"""Maximal refinement over numbers and bits."""

from dataclasses import replace
from itertools import product

import numpy as np
import pytest

from relseq import corpora
from relseq.operators import corpus as ops
from relseq.operators import dense, refine, typemining

D = "/root/testdata/sf0.001"


def shown(df):
    return {(r["skeleton"], tuple(r["vector"]), r["support"]) for r in df.collect()}


@pytest.mark.parametrize("kind,gap,span,k,unit", [("full", 3, None, 3, "event"), ("relations", 2, 5, 4, "element"), ("full", 1, 3, 3, "time"), ("relations", None, 4, 3, "event"), ("plain", 2, None, 4, "event")])
def test_equals_the_search_over_leaf_rows(spark, kind, gap, span, k, unit):
    mined = typemining.mine(ops.scenario(corpora.sessions(spark, D), kind), 0.10, gap, span, k, unit)
    assert mined.limits == (gap, span, unit)
    assert shown(refine.refine(mined)) == shown(refine.refine(replace(mined, limits=None)))


def test_no_leaf_row_is_made(spark, monkeypatch):
    mined = typemining.mine(ops.condensed(ops.scenario(corpora.sessions(spark, D), "relations")), 0.10, 3)
    want = shown(refine.refine(mined, algorithm="partitioned"))
    monkeypatch.setattr(refine, "leaf_rows", lambda *_: pytest.fail("leaf rows are made"))
    assert shown(refine.refine(mined)) == want


def test_small_parts_and_many_values(spark, monkeypatch):
    mined = typemining.mine(ops.condensed(corpora.sessions(spark, D)), 0.10, 3, None, 2)
    want = shown(refine.refine(replace(mined, limits=None)))
    corpus = mined.corpus
    wide = {s: len(ops.slot_names(list(refine.patterns.parse(s)[0]), corpus.trees, corpus.relations)) for s in mined.skeletons}
    nodes = dense.frequent_nodes(corpus, sorted(mined.skeletons), mined.threshold, mined.total, mined.limits)
    monkeypatch.setattr(dense, "PIECE_EVENTS", 20)
    monkeypatch.setattr(dense, "HELD_CELLS", 500)
    monkeypatch.setattr(dense, "SENT_CELLS", 100)
    parts = dense.lifted(corpus, sorted(mined.skeletons), nodes, mined.limits)
    assert parts.count() > 5 * len(mined.skeletons)
    assert shown(dense.refined(corpus, mined.skeletons, mined.threshold, mined.total, mined.limits, wide)) == want


def test_capped_occurrences_are_refined_as_before(spark):
    mined = typemining.mine(corpora.sessions(spark, D), 0.10, 3, None, 2, cap=(1, 0))
    assert mined.limits is None and refine.refine(mined).count() > 0


@pytest.mark.parametrize("deep", [1, 300])
def test_vectors_of_weighted_sequences(deep):
    rng = np.random.default_rng(7)
    nodes = [["a", "a/b", "a/c", "d"], sorted(["x", "y", *(f"y/{i:03}" for i in range(deep))])]
    sequences = np.sort(rng.integers(0, 90, 300))
    rows = np.stack([rng.integers(0, 5, 300), rng.integers(0, 4, 300)], axis=1).astype(np.uint32 if deep > 200 else np.uint8)
    weights = rng.integers(1, 9, 90)
    maps = dense.Bitmaps(*dense.merged(sequences, rows, weights), nodes)
    below = lambda own, c: c == "" or own == c or own.startswith(c + "/")
    names = [["", *own] for own in nodes]
    counts = {}
    for v in product(*[n[:8] for n in names]):
        hit = {s for s, r in zip(sequences, rows) if all(below(names[i][r[i]], c) for i, c in enumerate(v))}
        counts[v] = int(weights[sorted(hit)].sum()) if hit else 0
    theta = 60
    narrower = lambda v, w: v != w and all(below(b, a) for a, b in zip(v, w))
    want = {v: n for v, n in counts.items() if n >= theta and not any(m >= theta and narrower(v, w) for w, m in counts.items())}
    assert {tuple(v): n for v, n in dense.maximal(maps, theta, nodes)} == want


def test_supports_by_table_and_by_pairs(monkeypatch):
    rng = np.random.default_rng(3)
    at_depth = np.array([[0, 0, 1, -1], [2, 3, -1, -1]])
    sequences, words, weights = rng.integers(0, 20, 100), rng.integers(0, 4, 100), rng.integers(1, 5, 20)
    told = dense.supports(sequences, words, at_depth, weights, 4)
    monkeypatch.setattr(dense, "MARKED", 0)
    assert told.tolist() == dense.supports(sequences, words, at_depth, weights, 4).tolist()


def test_grid_relations_runs_settings_side_by_side(spark, monkeypatch):
    from relseq import workloads
    from relseq.operators import costs

    monkeypatch.setattr(refine, "leaf_rows", lambda *_: pytest.fail("leaf rows are made"))
    running, most, run = [], [], costs.run_cell

    def watched(corpus, cell):
        running.append(cell)
        most.append(len(running))
        try:
            return run(corpus, cell)
        finally:
            running.remove(cell)

    monkeypatch.setattr(costs, "run_cell", watched)
    cells = lambda *_: [workloads.Cell("gap", "relations", ms, max_gap=g, max_events=2) for ms in (0.3, 0.4) for g in (1, 2)]
    one = {tuple(r)[:9] for r in workloads.run_grid(spark, D, cells()).collect()}
    assert max(most) == 1
    assert {tuple(r)[:9] for r in workloads.run_grid(spark, D, cells(), at_once=4).collect()} == one
    assert max(most) > 1


def test_grid_span_relations_grows_no_row(spark, monkeypatch):
    """Spans without a gap: every later event is looked at, and no leaf row is made."""
    from relseq import workloads

    cells = [workloads.Cell("span", "relations", 0.3, max_span=w, max_events=3) for w in (2, 4)]
    mined = [typemining.mine(ops.condensed(ops.scenario(corpora.weeks(spark, D), "relations")), 0.3, None, c.max_span, 3) for c in cells]
    want = [refine.refine(replace(m, limits=None)).count() for m in mined]
    monkeypatch.setattr(refine, "leaf_rows", lambda *_: pytest.fail("leaf rows are made"))
    got = workloads.run_grid(spark, D, cells, "weeks", 2).collect()
    assert [r["n_patterns"] for r in got] == want and want[0] < want[1]
