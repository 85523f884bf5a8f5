import pytest
from hypothesis import given
from hypothesis import strategies as st

from relseq.functions import taxonomy
from relseq.operators import baselines, matching, patterns


def test_candidate_space_of_two_types():
    level = {patterns.parse("A"), patterns.parse("F")}
    sizes = [len(level)]
    for _ in range(3):
        level = set(patterns.extend(level, True))
        sizes.append(len(level))
    assert sizes == [2, 7, 24, 82]


def find(types, txns, text, gap=None, span=None, running=True):
    return matching.search_one(types, txns, list(range(1, len(types) + 1)), patterns.parse(text), gap, span, running)[0]


def test_four_equal_events():
    t, x = ["T"] * 4, [1] * 4
    assert [len(find(t, x, "T T", g, s)) for g, s in ((None, None), (1, None), (2, None), (None, 2))] == [6, 3, 5, 5]


def test_separators_must_agree():
    t, x = ["a", "b", "c", "c", "d"], [1, 1, 2, 3, 3]
    assert find(t, x, "a ; c") == [[1, 3], [1, 4]]
    assert find(t, x, "b c") == []
    assert find(t, x, "a b ; d") == [[1, 2, 5]]
    assert find(t, x, "c d") == [[4, 5]]
    assert find(t, x, "c ; d") == [[3, 5]]


def test_type_counts_reject_without_search():
    found, steps, pruned = matching.search_one(["a", "b", "c", "c", "d"], [1, 1, 2, 3, 3], [1, 2, 3, 4, 5], patterns.parse("c ; c ; c"), None, None, True)
    assert (found, steps, pruned) == ([], 1, 1)


@pytest.mark.parametrize("k,gap,span,exact", [(3, 3, None, 54), (3, None, 5, 60), (3, None, None, 120)])
def test_bounds(k, gap, span, exact):
    n = len(find(["T"] * 10, [1] * 10, "T T T", gap, span))
    assert n == exact <= patterns.occurrence_bound(10, k, gap, span)
    assert patterns.occurrence_bound(10, 3, 3, form="published") == 28 and patterns.occurrence_bound(10, 3, 3) == 72


def test_monotone_constraints_only():
    universe = [patterns.parse(s) for s in ("A ; A", "A ; F", "F ; F", "A ; A ; F")]
    with pytest.raises(ValueError):
        patterns.check_constraint(lambda s: len(set(s[0])) >= 2, universe)
    patterns.check_constraint(lambda s: len(s[0]) <= 3, universe)


@given(st.lists(st.tuples(st.sampled_from("AF"), st.booleans()), min_size=1, max_size=9), st.sampled_from(["A ; F", "A A", "F ; A ; F", "A F", "A ; A F"]), st.one_of(st.none(), st.integers(1, 4)))
def test_search_agrees_with_presence_and_needs_no_pruning(events, text, gap):
    txns, t = [], 0
    for i, (_, brk) in enumerate(events):
        t += 1 if brk or i == 0 else 0
        txns.append(t)
    types = [e[0] for e in events]
    found = find(types, txns, text, gap)
    assert found == find(types, txns, text, gap, running=False)
    assert bool(found) == baselines.reachable(types, txns, patterns.parse(text), gap)


@given(st.lists(st.tuples(st.sampled_from("AF"), st.booleans()), min_size=1, max_size=6))
def test_text_form_round_trip(events):
    s = (tuple(e[0] for e in events), tuple(e[1] for e in events[1:]))
    assert patterns.parse(patterns.render(s)) == s


def test_prefix_tree_text():
    paths = taxonomy.parse_prefix_tree("Any(Known(low,mid,high),Unknown)")
    assert paths == ["Known", "Known/low", "Known/mid", "Known/high", "Unknown"]
    assert taxonomy.render_prefix_tree(paths) == "Any(Known(low,mid,high),Unknown)"
    with pytest.raises(ValueError):
        taxonomy.parse_prefix_tree("Any(a,b")


def test_dag():
    dag = taxonomy.Dag.of([("p1", "t1"), ("p1", "b1"), ("p2", "t1"), ("p2", "b1"), ("p3", "t2"), ("t1", "Any"), ("t2", "Any"), ("b1", "Any")])
    assert dag.common_ancestor({"p1", "p3"}) == "Any"
    assert dag.most_specific(set.intersection(dag.above("p1"), dag.above("p2"))) == {"t1", "b1"}


def test_thresholds():
    assert patterns.threshold(0.10, 1500) == 150 and patterns.threshold(0.045, 1500) == 68 and patterns.threshold(7, 1500) == 7
    assert patterns.threshold(0.10, 1500, strict=True) == 151
