"""Corpora of types and transactions only, and what is counted on them."""

from relseq import corpora
from relseq.operators import baselines, refine, typemining
from relseq.operators import corpus as ops

D = "/root/testdata/sf0.001"


def shapes(corpus):
    return {(tuple((e.txn, e.type) for e in r.events), r.weight) for r in corpus.sequences.collect()}


def test_session_types_equal_condensed_sessions(spark):
    assert shapes(corpora.session_types(spark, D)) == shapes(ops.condensed(ops.scenario(corpora.sessions(spark, D), "plain")))


def test_crosscheck_brings_no_large_prefix_to_one_task(spark, monkeypatch):
    from pyspark.ml.fpm import PrefixSpan

    given = []
    found = PrefixSpan.findFrequentSequentialPatterns
    monkeypatch.setattr(PrefixSpan, "findFrequentSequentialPatterns", lambda self, rows: given.append(self.getMaxLocalProjDBSize()) or found(self, rows))
    each = baselines.prefixspan(corpora.sessions(spark, D), 0.10)
    monkeypatch.setattr(baselines, "LOCAL_ITEMS", 3)
    less = baselines.prefixspan(corpora.session_types(spark, D), 0.10)
    assert sorted(each.collect()) == sorted(less.collect()) and given == [500_000, 3]


def test_repeated_rows(spark, monkeypatch):
    monkeypatch.setattr(baselines, "REPEATS", 3)
    rows = spark.createDataFrame([("a", 1), ("b", 3), ("c", 7)], "sequence string, n long")
    assert sorted(r.sequence for r in baselines.repeated(rows).collect()) == list("abbbccccccc")


def test_order_types_equal_condensed_orders(spark):
    assert shapes(corpora.orders_year_types(spark, D)) == shapes(ops.condensed(ops.scenario(corpora.orders_year(spark, D), "plain")))


def test_numbers_stand_for_equal_paths(spark):
    rows = [(1, "x"), (2, "x"), (3, "y"), (3, "x"), (4, "z"), (4, "w"), (None, "v")]
    named = corpora.numbered(spark.createDataFrame(rows, "k long, path string"), "k", "path").collect()
    paths = {k: {p for j, p in rows if j == k} for k in (1, 2, 3, 4)}
    codes = {k: {r.path for r in named if r.k == k} for k in paths}
    assert all(len(codes[k]) == len(paths[k]) and len(codes[k] & codes[j]) == len(paths[k] & paths[j]) for k in paths for j in paths)


def test_maximal_vectors_are_found_without_all_frequent_ones(spark, monkeypatch):
    mined = typemining.mine(ops.condensed(corpora.sessions(spark, D)), 0.10, 3, None, 2)
    told = lambda df: sorted((r["skeleton"], tuple(r["vector"]), r["support"]) for r in df.collect())
    each = told(refine.keep(refine.refine(mined, "all"), "maximal"))
    assert max(n for _, n in mined.skeletons.values()) >= mined.stored > 0
    monkeypatch.setattr(refine, "keep", None)  # no exchange of all frequent vectors
    assert told(refine.refine(mined, "maximal")) == each
