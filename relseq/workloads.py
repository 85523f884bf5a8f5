"""The experiment workloads and operator checks as queries on the given tables."""

from __future__ import annotations

from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor
from dataclasses import replace
from functools import partial

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from relseq import corpora
from relseq.functions import taxonomy
from relseq.functions.relations import oriented
from relseq.operators import baselines, costs, matching, patterns, patternsets, refine, typemining
from relseq.operators import corpus as ops
from relseq.operators.costs import Cell
from relseq.operators.typemining import Mined
from relseq.sources.tables import read_table
from relseq.streaming import sequences as streams
from relseq.streaming.state import scratch

MS_GRID = (0.045, 0.09, 0.18, 0.2252, 0.2703)
MG_GRID = (1, 2, 3, 4, 5)
SPAN_GRID = (10, 13, 16, 19)
SWEEPS = ("gap", "span", "support", "size")
AT_ONCE = 4  # settings of a grid whose clock is not shown
KEY_RANGE = 10_000  # keys whose neighbours one window finds
LAMBDA = lambda: F.array_join(F.transform("lambda", lambda p: p.cast("string")), ",")


def _union(frames: list[DataFrame]) -> DataFrame:
    out = frames[0]
    for f in frames[1:]:
        out = out.unionByName(f)
    return out


def mined_sessions(spark, directory, ms, gap, k, kind="full", span=None) -> Mined:
    return typemining.mine(ops.scenario(corpora.sessions(spark, directory), kind), ms, gap, span, k)


def kept(corpus: ops.Corpus) -> ops.Corpus:
    return replace(corpus, sequences=corpus.sequences.persist())


def shown(vectors: DataFrame) -> DataFrame:
    return vectors.select("skeleton", F.array_join("vector", "|").alias("vector"), "support")


def two_and_more(df: DataFrame) -> DataFrame:
    return df.where(F.contains("skeleton", F.lit(" ")))


# -- corpora and views --------------------------------------------------------------------------------------


def corpus_profile(spark: SparkSession, d: str) -> DataFrame:
    return costs.corpus_stats(corpora.sessions(spark, d))


def length_histogram(spark: SparkSession, d: str) -> DataFrame:
    return costs.length_histogram(corpora.sessions(spark, d))


def canonical_events(spark: SparkSession, d: str) -> DataFrame:
    return ops.unpack(corpora.sessions(spark, d)).select("seq_id", "pos", "txn", "type", F.col("concepts")[0].alias("concept"), "event_id")


def type_view(spark: SparkSession, d: str) -> DataFrame:
    return corpora.sessions(spark, d).sequences.select("seq_id", ops.type_view(F.col("events")).alias("view"), "n_events", ops.n_elements().alias("n_elements"))


def element_index(spark: SparkSession, d: str) -> DataFrame:
    return ops.unpack(corpora.sessions(spark, d)).select("seq_id", "pos", ops.element_index(F.col("pos"), F.col("txn")).alias("element"))


def relation_profile(spark: SparkSession, d: str) -> DataFrame:
    """Pairs of events of a sequence by types and relation concept."""
    c = corpora.sessions(spark, d)
    relate = oriented(list(c.relations))
    pairs = F.flatten(F.transform("events", lambda b: F.transform(F.slice("events", 1, b["pos"] - 1), lambda a: F.struct(F.least(a["type"], b["type"]).alias("a"), F.greatest(a["type"], b["type"]).alias("b"), F.element_at(relate(a, b), 1).alias("concept")))))
    return c.sequences.select(F.explode(pairs).alias("x")).groupBy(F.col("x.a").alias("type_a"), F.col("x.b").alias("type_b"), "x.concept").agg(F.count("*").alias("pairs"))


def full_view_sizes(spark: SparkSession, d: str) -> DataFrame:
    """Sequences of the full view and the relation arrays they hold, which is why relations stay lazy."""
    c = corpora.sessions(spark, d)
    view = ops.full_view(F.col("events"), oriented(list(c.relations)))
    return c.sequences.select("seq_id", F.aggregate(view, F.lit(0), lambda n, e: n + F.size(e["relations"])).alias("relations"))


# -- taxonomies ---------------------------------------------------------------------------------------------


def taxonomy_stats(spark: SparkSession, d: str) -> DataFrame:
    events = corpora.event_days(read_table(spark, d, "events"), 3).select("type", F.col("concepts")[0].alias("concept"))
    part = read_table(spark, d, "part").withColumn("p_partkey", F.col("p_partkey").cast("string"))
    trees = [
        taxonomy.from_paths(events.where("type = 'A'"), tax_id="action"),
        taxonomy.from_paths(events.where("type = 'F'"), tax_id="fault"),
        taxonomy.from_columns(part, ["p_type", "p_brand", "p_partkey"], "part"),
        taxonomy.from_prefix_tree(spark, corpora.CROSS_TREE, "cross"),
        taxonomy.from_prefix_tree(spark, "Any(=,≠)", "identity"),
    ]
    return taxonomy.stats(_union(trees))


def taxonomy_closure_geo(spark: SparkSession, d: str) -> DataFrame:
    n, r = read_table(spark, d, "nation"), read_table(spark, d, "region")
    tree = taxonomy.from_columns(n.join(r, F.col("n_regionkey") == F.col("r_regionkey")), ["r_name", "n_name"], "geo")
    return taxonomy.closure(tree)


def taxonomy_heap(spark: SparkSession, d: str) -> DataFrame:
    """The fault tree over the keys of all events, errors or not: their heap nodes and what lies above."""
    k = F.get_json_object("props", "$.k").cast("long")
    keys = read_table(spark, d, "events").select((k + 4).alias("node")).where("node is not null").distinct()
    return taxonomy.stats(taxonomy.heap_of(keys, "node", "fault"))


def dag_common_ancestor(spark: SparkSession, d: str) -> DataFrame:
    """Parts under two parents, type and brand, which lie under ``Any``: what each part has in common with the next
    one by key. ``common`` is the deepest shared concept, ties by name; ``conjunction`` all most specific ones."""
    part = read_table(spark, d, "part").groupBy("p_partkey").agg(F.array_sort(F.array_distinct(F.concat(F.collect_set("p_type"), F.collect_set("p_brand")))).alias("parents"))
    own = part.where("p_partkey is not null").select("p_partkey", "parents", F.floor(F.col("p_partkey") / KEY_RANGE).alias("range"))
    # Neighbours inside a range of keys by its own window; across ranges by one row a range.
    before = F.lag(F.struct("p_partkey", "parents")).over(Window.partitionBy("range").orderBy("p_partkey"))
    ends = own.groupBy("range").agg(F.max_by(F.struct("p_partkey", "parents"), "p_partkey").alias("end"))
    ends = ends.select("range", F.lag("end").over(Window.orderBy("range")).alias("end"))
    pairs = own.withColumn("before", before).join(ends, "range").select(F.coalesce("before", "end").alias("a"), F.struct("p_partkey", "parents").alias("b")).where("a is not null")
    shared = F.array_sort(F.array_intersect("a.parents", "b.parents"))
    name = lambda x: F.concat(F.lit("part "), F.col(x)["p_partkey"].cast("string"))
    return pairs.select(name("a").alias("a"), name("b").alias("b"), F.coalesce(F.get(shared, 0), F.lit("Any")).alias("common"), F.when(F.size(shared) > 0, F.array_join(shared, " & ")).otherwise("Any").alias("conjunction"))


# -- matching -----------------------------------------------------------------------------------------------

ALL_K2 = ["A A", "A F", "F F", "A ; A", "A ; F", "F ; A", "F ; F"]


def occurrences_k2(spark: SparkSession, d: str) -> DataFrame:
    rows = matching.occurrences(corpora.sessions(spark, d), ALL_K2, max_gap=1)
    return rows.select("seq_id", "skeleton", LAMBDA().alias("positions"))


def occurrences_k3_gap2(spark: SparkSession, d: str, strategy: str = "grow") -> DataFrame:
    three = [patterns.render(s) for s in patterns.extend({patterns.parse(s) for s in ALL_K2}, True)]
    rows = matching.occurrences(corpora.sessions(spark, d), three, max_gap=2, strategy=strategy)
    return rows.groupBy("skeleton").agg(F.count("*").alias("occurrences"), F.count_distinct("seq_id").alias("support"))


def occurrences_span(spark: SparkSession, d: str) -> DataFrame:
    rows = matching.occurrences(corpora.sessions(spark, d), ["A ; A ; F", "A A F", "F ; A ; A"], max_span=4)
    return rows.select("seq_id", "skeleton", LAMBDA().alias("positions"))


def occurrences_units(spark: SparkSession, d: str) -> DataFrame:
    """The same skeleton under a gap of 2 in each unit."""
    c = corpora.sessions(spark, d)
    return _union([matching.occurrences(c, ["A ; F"], 2, unit=u).groupBy("skeleton").agg(F.count("*").alias("occurrences")).withColumn("unit", F.lit(u)) for u in matching.UNITS])


def multiset_candidates(spark: SparkSession, d: str) -> DataFrame:
    c = corpora.sessions(spark, d)
    names = ["A ; F", "F ; F", "A A A", "F ; F ; F", "A ; A ; F"]
    return _union([matching.multiset_filter(c, [patterns.parse(s)]).agg(F.count("*").alias("sequences")).select(F.lit(s).alias("skeleton"), "sequences") for s in names])


def parent_lists(spark: SparkSession, d: str) -> DataFrame:
    return typemining.parent_lists(mined_sessions(spark, d, 0.10, 3, 2), 3)


# -- stage 1 ------------------------------------------------------------------------------------------------


def skeletons(spark: SparkSession, d: str, ms: float, gap: int | None, k: int = 3) -> DataFrame:
    return mined_sessions(spark, d, ms, gap, k).table()


def skeletons_ms_sweep(spark: SparkSession, d: str) -> DataFrame:
    """Unlimited gap and span: what a higher support keeps is part of what the lowest keeps."""
    m = mined_sessions(spark, d, MS_GRID[0], None, 3)
    t = m.table()
    return _union([t.where(F.col("support") >= patterns.threshold(ms, m.total)).groupBy("n_events").agg(F.count("*").alias("skeletons"), F.sum("occurrences").alias("occurrences")).withColumn("ms", F.lit(ms)) for ms in MS_GRID])


def skeletons_span_sweep(spark: SparkSession, d: str) -> DataFrame:
    c = kept(ops.condensed(ops.scenario(corpora.weeks(spark, d), "plain")))
    cells = [(ms, w) for ms in (0.10, 0.18) for w in SPAN_GRID]
    return _union([typemining.mine(c, ms, None, w, 3).table().groupBy("n_events").agg(F.count("*").alias("skeletons"), F.sum("occurrences").alias("occurrences")).withColumns({"ms": F.lit(ms), "span": F.lit(w)}) for ms, w in cells])


def skeletons_orders_year(spark: SparkSession, d: str) -> DataFrame:
    return typemining.mine(corpora.orders_year_types(spark, d), 0.10, 3, None, 3).table()


def skeletons_dialogues(spark: SparkSession, d: str) -> DataFrame:
    return typemining.mine(corpora.dialogues(spark, d), 0.10, 3, None, 3).table()


def skeletons_size_sweep(spark: SparkSession, d: str) -> DataFrame:
    c = corpora.sessions(spark, d)
    user, bucket = F.split("seq_id", "-")[0].cast("long"), F.split("seq_id", "-")[1].cast("long")
    parts = []
    for tenths in range(1, 11):
        m = typemining.mine(ops.sample(c, tenths, user * 7 + bucket * 3), 0.10, 3, None, 3)
        parts.append(m.table().withColumn("tenths", F.lit(tenths)))
    return _union(parts)


def gap_subpattern_violations(spark: SparkSession, d: str) -> DataFrame:
    m = mined_sessions(spark, d, 0.10, 1, 3)
    return typemining.interior_violations(m, 1)


# -- stage 2 ------------------------------------------------------------------------------------------------


def item_support(spark: SparkSession, d: str) -> DataFrame:
    return two_and_more(refine.item_support(refine.leaf_rows(mined_sessions(spark, d, 0.10, 3, 2))))


def item_vocabulary(spark: SparkSession, d: str) -> DataFrame:
    return two_and_more(refine.vocabulary(refine.leaf_rows(mined_sessions(spark, d, 0.10, 1, 2)))).select("skeleton", "item_id", "slot", "concept")


def refined(spark: SparkSession, d: str, kind: str, scenario: str, ms: float, gap: int | None, k: int, algorithm: str = "vectors") -> DataFrame:
    return shown(two_and_more(refine.refine(mined_sessions(spark, d, ms, gap, k, scenario), kind, algorithm)))


def example_patterns(spark: SparkSession, d: str) -> DataFrame:
    """Two fixed patterns: a fault before an action it matches; two actions in successive transactions, then a
    fault under 0/1 that matches the first."""
    c = corpora.sessions(spark, d)
    asked = [("fault, later matched action", "F ; A", ["", "", "Matched"]), ("two actions, then a fault of one kind", "A ; A ; F", ["", "", "", "0/1", "Matched", ""])]
    parts = []
    for name, skeleton, vector in asked:
        occ = matching.occurrences(c, [skeleton]).groupBy("seq_id").agg(F.collect_list(F.struct("skeleton", "lambda")).alias("found"))
        rows = c.sequences.join(occ, "seq_id").select("seq_id", "events", F.col("found").cast(matching.OCCURRENCE).alias("found"))
        leafs = refine.leaf_rows(Mined(c, 0, 0, {}, rows))
        parts.append(refine.match(leafs, skeleton, vector).agg(F.count("*").alias("support")).select(F.lit(name).alias("pattern"), "support"))
    return _union(parts)


def specialised_share(spark: SparkSession, d: str) -> DataFrame:
    m = mined_sessions(spark, d, 0.10, 3, 2)
    return costs.specialised_share(two_and_more(refine.to_patterns(m, refine.refine(m))))


def topk_patterns(spark: SparkSession, d: str) -> DataFrame:
    """The five best-supported refinements of each skeleton of two events."""
    m = mined_sessions(spark, d, 0.10, 3, 2)
    found = shown(two_and_more(refine.refine(m)))
    place = F.row_number().over(Window.partitionBy("skeleton").orderBy(F.desc("support"), "vector"))
    return found.withColumn("place", place).where("place <= 5")


def rollup_support_by_level(spark: SparkSession, d: str) -> DataFrame:
    """Sequences under every node of the action tree, by rolling the hierarchy's levels up."""
    e = ops.unpack(corpora.sessions(spark, d)).where("type = 'A'").select("seq_id", F.split(F.col("concepts")[0], "/").alias("p"))
    out = e.select("seq_id", F.col("p")[0].alias("family"), F.col("p")[1].alias("kind"), F.col("p")[2].alias("quarter")).distinct()
    return out.rollup("family", "kind", "quarter").agg(F.count_distinct("seq_id").alias("support"))


def flagship_of(spark: SparkSession, d: str, k: int | None = None, ms: float = 0.10, gap: int = 3) -> DataFrame:
    m = typemining.mine(kept(ops.condensed(corpora.sessions(spark, d))), ms, gap, None, k)  # packed once for both stages
    return refine.to_patterns(m, refine.refine(m)).select("skeleton", "pattern", "n_events", "support", "support_pct", "specialised")


def flagship(spark: SparkSession, d: str) -> DataFrame:
    """Maximal refinements of all frequent skeletons, gap 3, support 10 %."""
    return flagship_of(spark, d)


def generic_refinement(spark: SparkSession, d: str) -> DataFrame:
    """The second stage alone, on structures that are no sequences: a part line under its order, by three trees."""
    li, part = read_table(spark, d, "lineitem"), read_table(spark, d, "part")
    rows = li.join(part, F.col("l_partkey") == F.col("p_partkey")).select(F.lit("line").alias("skeleton"), F.col("l_orderkey").cast("string").alias("seq_id"), F.array(F.concat_ws("/", "p_type", "p_brand"), "l_returnflag", "l_linestatus").alias("leaf")).distinct()
    return shown(refine.refine_any(rows, 600, "maximal"))


# -- baselines ----------------------------------------------------------------------------------------------


def presence_vs_occurrences(spark: SparkSession, d: str) -> DataFrame:
    c = corpora.sessions(spark, d)
    a = baselines.presence(c, ALL_K2, 2)
    b = matching.occurrences(c, ALL_K2, 2).groupBy("skeleton").agg(F.count("*").alias("occurrences"))
    return a.join(b, "skeleton")


def presence_forward(spark: SparkSession, d: str) -> DataFrame:
    return baselines.presence_forward(corpora.sessions(spark, d), ALL_K2, 2)


def first_occurrence_loss(spark: SparkSession, d: str) -> DataFrame:
    """Support of each relation concept when only first occurrences are refined, beside the true one."""
    m = mined_sessions(spark, d, 0.10, 3, 2, "relations")
    full = two_and_more(refine.item_support(refine.leaf_rows(m)))
    less = two_and_more(refine.item_support(refine.leaf_rows(baselines.first_occurrence(m)))).withColumnRenamed("support", "first_support")
    return full.join(less, ["skeleton", "slot", "concept"], "left").withColumn("first_support", F.coalesce("first_support", F.lit(0).cast("long")))


def row_vs_sequence_support(spark: SparkSession, d: str) -> DataFrame:
    m = mined_sessions(spark, d, 0.10, 3, 2, "relations")
    relate = oriented(list(m.corpus.relations))
    made = F.transform("found", lambda o: F.struct(o["skeleton"].alias("skeleton"), ops.concept_view(F.col("events"), o["lambda"], relate, False).alias("leaf")))
    leafs = m.rows.select("seq_id", F.explode(made).alias("x")).select("x.skeleton", "seq_id", "x.leaf")
    return two_and_more(baselines.row_support(leafs))


def prefixspan_crosscheck(spark: SparkSession, d: str) -> DataFrame:
    """Skeletons on which the library's pattern growth and this miner can be compared, with both supports."""
    c = kept(corpora.session_types(spark, d))
    theirs = baselines.prefixspan(c, 0.10).withColumnRenamed("support", "prefixspan_support")
    return baselines.plain(c, 0.10).table().join(theirs, ["skeleton", "n_events"]).select("skeleton", "support", "prefixspan_support")


def pattern_growth(spark: SparkSession, d: str, gap: int | None = None) -> DataFrame:
    found = baselines.prefix_growth(corpora.sessions(spark, d), 0.10, gap, 3)
    return spark.createDataFrame(sorted(found.items()), "skeleton string, support long")


def pruning_ablation(spark: SparkSession, d: str) -> DataFrame:
    return baselines.pruning_steps(corpora.sessions(spark, d), ["A ; F ; F", "F ; F ; F"], 3)


# -- remedies and measures ----------------------------------------------------------------------------------


def crowded_remedy(spark: SparkSession, d: str) -> DataFrame:
    return typemining.mine(ops.drop_crowded(corpora.sessions(spark, d), 6), 0.10, 3, None, 3).table()


def long_remedy(spark: SparkSession, d: str) -> DataFrame:
    return typemining.mine(ops.drop_long(corpora.sessions(spark, d), 8), 0.10, 3, None, 3).table()


def run_length_remedy(spark: SparkSession, d: str) -> DataFrame:
    m = typemining.mine(corpora.sessions(spark, d), 0.10, 3, None, 3, drop_runs=3)
    return m.table()


def cap_remedy(spark: SparkSession, d: str) -> DataFrame:
    """Two occurrences of a skeleton in a sequence at most: fewer occurrences, and what is lost."""
    c = kept(ops.condensed(ops.scenario(corpora.sessions(spark, d), "plain")))
    free, capped = typemining.mine(c, 0.10, 3), typemining.mine(c, 0.10, 3, cap=(2, 0))
    less = capped.table().select("skeleton", F.col("support").alias("capped_support"), F.col("occurrences").alias("capped_occurrences"))
    return free.table().join(less, "skeleton", "left")


def complexity_bounds(spark: SparkSession, d: str) -> DataFrame:
    """Bounds beside the counts on one type in one transaction, where the unconstrained bound is reached, for the
    lengths of 3 to 8 events that sessions have."""
    lengths = corpora.sessions(spark, d).sequences.where("n_events between 3 and 8").select("n_events").distinct()
    rows = []
    for n in sorted(r["n_events"] for r in lengths.collect()):
        for k in (2, 3):
            for gap, span in ((None, None), (2, None), (3, None), (None, 4)):
                exact = len(matching.search_one(["T"] * n, [1] * n, list(range(1, n + 1)), (("T",) * k, (False,) * (k - 1)), gap, span, False)[0])
                rows.append((n, k, gap or 0, span or 0, exact, patterns.occurrence_bound(n, k, gap, span), patterns.occurrence_bound(n, k, gap, span, "published")))
    return spark.createDataFrame(rows, "n int, k int, gap int, span int, exact long, corrected long, published long")


def stream_equals_batch(spark: SparkSession, d: str) -> DataFrame:
    """Supports after replaying events as a stream of closed windows, beside the batch ones."""
    events = read_table(spark, d, "events")
    like = corpora.sessions(spark, d)
    names = ["A ; F", "A A", "F ; A"]
    path = scratch(spark)
    closed = streams.follow(corpora.event_days(streams.replay(spark, d, "events", events.schema), 3))
    sink = streams.Support(like, names, 2, f"{path}/out")
    closed.writeStream.outputMode("update").foreachBatch(sink).option("checkpointLocation", f"{path}/state").trigger(availableNow=True).start().awaitTermination()
    batch = streams.batch_counts(like, names, 2).select("skeleton", F.col("support").alias("batch_support"), F.col("occurrences").alias("batch_occurrences"))
    return sink.total(spark).join(batch, "skeleton")


def run_grid(spark: SparkSession, d: str, cells: list[Cell], corpus: str = "sessions", at_once: int = 1) -> DataFrame:
    """Both stages for each setting, cold, with counts and timings; the packed corpus is made once. With settings
    ``at_once``, whose small jobs fill each other's gaps, timings tell nothing of a setting by itself."""
    made = getattr(corpora, corpus)(spark, d)
    base = replace(made, sequences=made.sequences.persist()) if any(c.tenths < 10 for c in cells) else made
    whole = {kind: kept(ops.condensed(ops.scenario(base, kind))) for kind in sorted({c.scenario for c in cells if c.tenths == 10})}

    def measured(cell: Cell) -> tuple:
        c = whole.get(cell.scenario)
        if cell.tenths < 10:
            c = kept(ops.condensed(ops.sample(ops.scenario(base, cell.scenario), cell.tenths, F.split("seq_id", "-")[0].cast("long") * 7 + F.split("seq_id", "-")[1].cast("long") * 3)))
        r = costs.run_cell(c, cell)
        if cell.tenths < 10:
            c.sequences.unpersist()
        return (r.workload, r.scenario, r.min_support, r.max_gap or 0, r.max_span or 0, 10 * r.tenths, r.skeletons, r.occurrences, r.patterns, float(r.specialised), r.stage1, r.stage2, r.stage1 + r.stage2)

    if at_once > 1:
        for c in whole.values():
            c.size()  # kept before several settings ask for it
        with ThreadPoolExecutor(at_once) as pool:
            rows = list(pool.map(measured, cells))
    else:
        rows = [measured(cell) for cell in cells]
    for c in (base, *whole.values()):
        c.sequences.unpersist()
    return spark.createDataFrame(rows, "workload string, scenario string, ms double, mg int, span int, sample_pct int, n_skeletons long, n_occurrences long, n_patterns long, specialised_share double, t_stage1 double, t_stage2 double, t_total double")


def gap_sweep_cells(ms: float, kind: str, k: int | None = None) -> list[Cell]:
    return [Cell(f"gap sweep {ms:g}", kind, ms, max_gap=g, max_events=k) for g in MG_GRID]


def all_cells(k: int = 3) -> list[Cell]:
    """The whole grid: gap and span sweeps at two supports, support and size sweeps, in both scenarios."""
    out: list[Cell] = []
    for kind in ("relations", "full"):
        for ms in (0.10, 0.18):
            out += gap_sweep_cells(ms, kind, k)
            out += [Cell(f"span sweep {ms:g}", kind, ms, max_span=w, max_events=k) for w in SPAN_GRID]
        out += [Cell("support sweep", kind, ms, max_events=k) for ms in MS_GRID]
        out += [Cell("size sweep", kind, 0.10, max_gap=3, tenths=t, max_events=k) for t in range(1, 11)]
    return out


def grid_relations(spark: SparkSession, d: str) -> DataFrame:
    """The gap sweep of the relations scenario, without its clock: patterns by setting."""
    return run_grid(spark, d, gap_sweep_cells(0.10, "relations") + gap_sweep_cells(0.18, "relations"), at_once=AT_ONCE).select("workload", "mg", "n_skeletons", "n_occurrences", "n_patterns")


def grid(spark: SparkSession, d: str, sweep: str, kind: str, k: int) -> DataFrame:
    """One of the published sweeps through both stages in one scenario, without its clock."""
    cells = [c for c in all_cells(k) if c.scenario == kind and c.workload.startswith(sweep)]
    found = run_grid(spark, d, cells, "weeks" if sweep == "span" else "sessions", AT_ONCE)
    return found.select("workload", "ms", "mg", "span", "sample_pct", "n_skeletons", "n_occurrences", "n_patterns")


def stage_shapes(timed: DataFrame) -> DataFrame:
    """(workload, scenario, settings, stage1_dominates, stage2_share): which stage takes the time, from ``run_grid``."""
    return timed.groupBy("workload", "scenario").agg(F.count("*").alias("settings"), F.sum((F.col("t_stage1") > F.col("t_stage2")).cast("long")).alias("stage1_dominates"), F.round(F.sum("t_stage2") / F.sum("t_total"), 4).alias("stage2_share"))


# -- comparing runs, first looks, streams ----------------------------------------------------------------------


def _rel2(spark, d, gap):
    return two_and_more(refine.refine(mined_sessions(spark, d, 0.10, gap, 2, "relations")))


def pattern_set_changes(spark: SparkSession, d: str) -> DataFrame:
    """Maximal refinements at gap 1 beside those at gap 3."""
    found = patternsets.changes(_rel2(spark, d, 1), _rel2(spark, d, 3))
    return found.withColumn("vector", F.array_join("vector", "|"))


def pattern_set_operations(spark: SparkSession, d: str) -> DataFrame:
    a, b = _rel2(spark, d, 1), _rel2(spark, d, 3)
    parts = [("union", patternsets.union(a, b)), ("intersection", patternsets.intersection(a, b)), ("difference", patternsets.difference(a, b))]
    return _union([x.select(F.lit(name).alias("operation"), "skeleton", F.array_join("vector", "|").alias("vector"), "support") for name, x in parts])


def approximate_item_support(spark: SparkSession, d: str) -> DataFrame:
    """Exact supports, and whether the sketched ones are near them."""
    leafs = refine.leaf_rows(mined_sessions(spark, d, 0.10, 3, 2))
    near = refine.approximate_item_support(leafs).withColumnRenamed("support", "guess")
    both = refine.item_support(leafs).join(near, ["skeleton", "slot", "concept"])
    return two_and_more(both).select("skeleton", "slot", "concept", "support", (F.abs(F.col("guess") - F.col("support")) <= F.greatest(F.lit(2.0), 0.1 * F.col("support"))).alias("near"))


def item_support_cube(spark: SparkSession, d: str) -> DataFrame:
    m = mined_sessions(spark, d, 0.10, 3, 2)
    return refine.support_cube(two_and_more(refine.leaf_rows(m)), m.total)


def outlier_cut(spark: SparkSession, d: str) -> DataFrame:
    """The length that 95 % of sequences do not exceed, and what a cut there leaves."""
    c = corpora.sessions(spark, d)
    kept = ops.drop_outliers(c, 0.95)
    return kept.sequences.agg(F.count("*").alias("sequences"), F.sum("n_events").cast("long").alias("events")).withColumn("longest", F.lit(ops.length_cut(c, 0.95)))


def length_bands(spark: SparkSession, d: str) -> DataFrame:
    return ops.length_bands(corpora.sessions(spark, d), 3)


def event_gaps(spark: SparkSession, d: str) -> DataFrame:
    """How many days lie between neighbouring events."""
    return ops.event_gaps(corpora.sessions(spark, d)).groupBy("day_gap").agg(F.count("*").alias("events"))


PARTIAL = [["error", "purchase"], ["error", "view", "error"], ["click", "click"]]
PARTIAL_SPAN = 36 * 3600


def stream_partial_matches(spark: SparkSession, d: str) -> DataFrame:
    """Occurrences of type sequences inside 36 hours, completed from a stream with a state for each user."""
    events = read_table(spark, d, "events")
    path = scratch(spark)
    live = streams.with_time(streams.replay(spark, d, "events", events.schema), "ts").withColumnRenamed("event_type", "type")
    found = streams.partial_matches(live.select("user_id", "event_id", "type", "at"), PARTIAL, PARTIAL_SPAN)
    found.writeStream.format("parquet").option("path", f"{path}/out").option("checkpointLocation", f"{path}/state").trigger(availableNow=True).start().awaitTermination()
    done = spark.read.schema("user_id long, skeleton string, event_ids array<long>").parquet(f"{path}/out")
    return done.groupBy("skeleton").agg(F.count("*").alias("occurrences"), F.count_distinct("user_id").alias("users"))


def extended_form(spark: SparkSession, d: str) -> DataFrame:
    """Pairs of generalised events in successive transactions, mined in the form where events carry their ancestors."""
    found = baselines.extended_mining(corpora.sessions(spark, d), 0.10, 2)
    return found.where("n_items = 2 and contains(pattern, ' ; ')").select("pattern", "support")


Query = Callable[[SparkSession, str], DataFrame]

QUERIES: dict[str, Query] = {
    "flagship_maximal_refinements": flagship,
    "corpus_profile": corpus_profile,
    "length_histogram": length_histogram,
    "canonical_events": canonical_events,
    "type_view": type_view,
    "element_index": element_index,
    "relation_profile": relation_profile,
    "full_view_sizes": full_view_sizes,
    "taxonomy_stats": taxonomy_stats,
    "taxonomy_closure_geo": taxonomy_closure_geo,
    "taxonomy_heap": taxonomy_heap,
    "dag_common_ancestor": dag_common_ancestor,
    "occurrences_k2": occurrences_k2,
    "occurrences_k3_gap2": occurrences_k3_gap2,
    "occurrences_k3_gap2_kernel": partial(occurrences_k3_gap2, strategy="kernel"),
    "occurrences_k3_gap2_join": partial(occurrences_k3_gap2, strategy="sql"),
    "occurrences_span": occurrences_span,
    "occurrences_units": occurrences_units,
    "multiset_candidates": multiset_candidates,
    "parent_lists": parent_lists,
    **{f"skeletons_k3_ms10_mg{g}": partial(skeletons, ms=0.10, gap=g) for g in MG_GRID},
    "skeletons_k4_ms18_mg3": partial(skeletons, ms=0.18, gap=3, k=4),
    "skeletons_all_ms18_mg1": partial(skeletons, ms=0.18, gap=1, k=None),
    "skeletons_all_ms18_mg3": partial(skeletons, ms=0.18, gap=3, k=None),
    "skeletons_all_ms10_mg3": partial(skeletons, ms=0.10, gap=3, k=None),
    "skeletons_ms_sweep": skeletons_ms_sweep,
    "skeletons_span_sweep": skeletons_span_sweep,
    "skeletons_orders_year": skeletons_orders_year,
    "skeletons_dialogues": skeletons_dialogues,
    "skeletons_size_sweep": skeletons_size_sweep,
    "gap_subpattern_violations": gap_subpattern_violations,
    "item_support": item_support,
    "item_vocabulary": item_vocabulary,
    "refine_all_rel_k3": partial(refined, kind="all", scenario="relations", ms=0.10, gap=3, k=3),
    "refine_closed_rel_k3": partial(refined, kind="closed", scenario="relations", ms=0.10, gap=3, k=3),
    "refine_maximal_rel_k3": partial(refined, kind="maximal", scenario="relations", ms=0.10, gap=3, k=3),
    "refine_maximal_rel_k3_backtrack": partial(refined, kind="maximal", scenario="relations", ms=0.10, gap=3, k=3, algorithm="backtrack"),
    "refine_maximal_rel_k3_levelwise": partial(refined, kind="maximal", scenario="relations", ms=0.18, gap=3, k=3, algorithm="levelwise"),
    "refine_maximal_rel_k3_partitioned": partial(refined, kind="maximal", scenario="relations", ms=0.10, gap=3, k=3, algorithm="partitioned"),
    "refine_all_full_k2": partial(refined, kind="all", scenario="full", ms=0.10, gap=3, k=2),
    "refine_closed_full_k2": partial(refined, kind="closed", scenario="full", ms=0.10, gap=3, k=2),
    "refine_maximal_full_k2": partial(refined, kind="maximal", scenario="full", ms=0.10, gap=3, k=2),
    "refine_maximal_full_k3": partial(refined, kind="maximal", scenario="full", ms=0.10, gap=3, k=3),
    "refine_maximal_full_k3_partitioned": partial(refined, kind="maximal", scenario="full", ms=0.10, gap=3, k=3, algorithm="partitioned"),
    "refine_taxonomic_only_k2": partial(refined, kind="maximal", scenario="taxonomic", ms=0.10, gap=3, k=2),
    "example_patterns": example_patterns,
    "specialised_share": specialised_share,
    "topk_patterns": topk_patterns,
    "rollup_support_by_level": rollup_support_by_level,
    "generic_refinement": generic_refinement,
    "presence_vs_occurrences": presence_vs_occurrences,
    "presence_forward": presence_forward,
    "first_occurrence_loss": first_occurrence_loss,
    "row_vs_sequence_support": row_vs_sequence_support,
    "prefixspan_crosscheck": prefixspan_crosscheck,
    "pattern_growth": pattern_growth,
    "pattern_growth_mg2": partial(pattern_growth, gap=2),
    "pruning_ablation": pruning_ablation,
    "crowded_remedy": crowded_remedy,
    "long_remedy": long_remedy,
    "run_length_remedy": run_length_remedy,
    "cap_remedy": cap_remedy,
    "complexity_bounds": complexity_bounds,
    "grid_relations": grid_relations,
    "stream_equals_batch": stream_equals_batch,
    **{f"grid_{sweep}_{kind}_k{k}": partial(grid, sweep=sweep, kind=kind, k=k) for sweep in SWEEPS for kind, k in (("relations", 3), ("full", 2))},
    "pattern_set_changes": pattern_set_changes,
    "pattern_set_operations": pattern_set_operations,
    "approximate_item_support": approximate_item_support,
    "item_support_cube": item_support_cube,
    "outlier_cut": outlier_cut,
    "length_bands": length_bands,
    "event_gaps": event_gaps,
    "stream_partial_matches": stream_partial_matches,
    "extended_form": extended_form,
}
