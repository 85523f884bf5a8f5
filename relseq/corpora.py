"""The corpora on the given tables. Each has the structure of the clinical data, not its meaning."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from relseq.functions import relations as rel
from relseq.functions.relations import Relation
from relseq.operators.corpus import Corpus, build, build_plain
from relseq.sources.tables import read_table

DAY0 = "2024-01-01"
CROSS_TREE = "Any(Matched(Higher,Equal,Lower),Unmatched)"


def event_days(events: DataFrame, days: int) -> DataFrame:
    """Long layout of ``events``: errors are faults F with heap concepts, the others actions A with four levels."""
    k = F.get_json_object("props", "$.k").cast("int")
    day = F.datediff(F.to_date("ts"), F.lit(DAY0).cast("date"))
    rows = events.select("event_id", "user_id", "event_type", "value", k.alias("k"), day.alias("day")).where("user_id is not null and event_type is not null and k is not null")
    fault = F.col("event_type") == "error"
    digits = F.substring(F.bin((F.col("k") + 4).cast("long")), 2, 99)
    heap = F.array_join(F.filter(F.split(digits, ""), lambda c: c != ""), "/")
    family = F.when(F.col("event_type").isin("view", "click"), "engage").otherwise("convert")
    action = F.concat_ws("/", family, "event_type", F.concat(F.lit("q"), F.expr("cast(k div 20 as string)")), F.lpad(F.expr("cast(k div 2 as string)"), 2, "0"))
    bucket = F.expr(f"day div {days}")
    return rows.select(
        F.concat_ws("-", F.col("user_id").cast("string"), bucket.cast("string")).alias("seq_id"), F.col("day").cast("long").alias("txn_key"), F.when(fault, "F").otherwise("A").alias("type"), F.array(F.when(fault, heap).otherwise(action)).alias("concepts"),
        F.struct(F.col("k").alias("k"), F.expr("cast(k div 10 as int)").alias("decade"), F.col("value").alias("value"), F.col("event_type").alias("name"), F.col("day").alias("day")).alias("attrs"), "event_id",
    )


def session_relations() -> list[Relation]:
    def outcome(a, f):
        return F.when(f["attrs"]["value"] > a["attrs"]["value"], "Higher").when(f["attrs"]["value"] < a["attrs"]["value"], "Lower").otherwise("Equal")

    cross = rel.lookup(lambda a, f: a["attrs"]["decade"] == f["attrs"]["decade"], outcome, "Matched", "Unmatched", ["Higher", "Equal", "Lower"])
    return [Relation("A", "F", *cross), Relation("A", "A", *rel.identity("name")), Relation("F", "F", *rel.identity("decade"))]


def sessions(spark: SparkSession, directory: str, days: int = 3) -> Corpus:
    return build(event_days(read_table(spark, directory, "events"), days), {"A": ["action"], "F": ["fault"]}, session_relations())


def session_types(spark: SparkSession, directory: str, days: int = 3) -> Corpus:
    """``sessions`` in the plain scenario, condensed."""
    return build_plain(event_days(read_table(spark, directory, "events"), days), {"A": ["action"], "F": ["fault"]})


def weeks(spark: SparkSession, directory: str) -> Corpus:
    return sessions(spark, directory, 7)


ORDER_TREES = {"O": ["priority", "status"], "L": ["part", "place"]}


def days(c: str) -> Column:
    return F.datediff(F.to_date(c), F.lit("1970-01-01").cast("date"))


def order_sequence() -> Column:
    return F.concat_ws("-", F.col("o_custkey").cast("string"), F.year("o_orderdate").cast("string"))


def line_concepts(spark: SparkSession, directory: str) -> tuple[DataFrame, DataFrame]:
    """Paths of parts and of suppliers."""
    part, supplier, nation, region = (read_table(spark, directory, t) for t in ("part", "supplier", "nation", "region"))
    where = supplier.join(nation, F.col("s_nationkey") == F.col("n_nationkey")).join(region, F.col("n_regionkey") == F.col("r_regionkey")).select("s_suppkey", F.concat_ws("/", "r_name", "n_name", "s_name").alias("place"))
    what = part.select("p_partkey", "p_brand", F.concat_ws("/", "p_type", "p_brand", F.col("p_partkey").cast("string")).alias("kind"))
    return what, where


def numbered(concepts: DataFrame, key: str, path: str) -> DataFrame:
    """(key, path) with a short name in the place of each path, equal where the paths are: the smallest key that has
    the path, and its place among the paths of that key, if that is not the first."""
    rows = concepts.where(F.col(key).isNotNull()).select(key, path)
    rows = rows.withColumn("at", F.dense_rank().over(Window.partitionBy(key).orderBy(path)))
    first = F.min(F.struct(key, "at")).over(Window.partitionBy(path))
    return rows.select(key, first.alias("first")).select(key, F.concat_ws("/", F.col("first")[key].cast("string"), F.when(F.col("first.at") > 1, F.col("first.at").cast("string"))).alias(path))


def orders_year(spark: SparkSession, directory: str) -> Corpus:
    """Orders and their lines by customer and year: two trees for each type, outcome relation by return flag."""
    orders, lines = read_table(spark, directory, "orders"), read_table(spark, directory, "lineitem")
    what, where = line_concepts(spark, directory)
    seq = order_sequence()
    none = F.lit(None)

    def attrs(order, status, flag, brand, day):
        return F.struct(order.cast("long").alias("order"), status.cast("string").alias("priority"), flag.cast("string").alias("flag"), brand.cast("string").alias("brand"), day.cast("int").alias("day"))

    o = orders.select(seq.alias("seq_id"), days("o_orderdate").cast("long").alias("txn_key"), F.lit("O").alias("type"), F.array("o_orderpriority", "o_orderstatus").alias("concepts"), attrs(F.col("o_orderkey"), F.col("o_orderpriority"), none, none, days("o_orderdate")).alias("attrs"), F.col("o_orderkey").cast("long").alias("event_id"))
    joined = lines.join(orders.select("o_orderkey", seq.alias("seq_id")), F.col("l_orderkey") == F.col("o_orderkey")).join(what, F.col("l_partkey") == F.col("p_partkey")).join(where, F.col("l_suppkey") == F.col("s_suppkey"))
    tie = F.col("l_orderkey") * 1000 + F.col("l_linenumber")
    li = joined.select("seq_id", days("l_shipdate").cast("long").alias("txn_key"), F.lit("L").alias("type"), F.array("kind", "place").alias("concepts"), attrs(F.col("l_orderkey"), none, F.col("l_returnflag"), F.col("p_brand"), days("l_shipdate")).alias("attrs"), tie.cast("long").alias("event_id"))
    linked = rel.lookup(lambda a, b: a["attrs"]["order"] == b["attrs"]["order"], lambda a, b: a["attrs"]["flag"], "Linked", "Unlinked", ["A", "N", "R"])
    relations = [Relation("L", "O", *linked), Relation("L", "L", *rel.identity("brand")), Relation("O", "O", *rel.identity("priority"))]
    return build(o.unionByName(li), ORDER_TREES, relations)


def orders_year_types(spark: SparkSession, directory: str) -> Corpus:
    """``orders_year`` in the plain scenario, condensed. Lines carry a number for each concept instead of its path."""
    orders, lines = read_table(spark, directory, "orders"), read_table(spark, directory, "lineitem")
    what, where = line_concepts(spark, directory)
    what, where = numbered(what, "p_partkey", "kind"), numbered(where, "s_suppkey", "place")
    seq = order_sequence()
    o = orders.select(seq.alias("seq_id"), days("o_orderdate").cast("long").alias("txn_key"), F.lit("O").alias("type"), F.array("o_orderpriority", "o_orderstatus").alias("concepts"))
    li = lines.select("l_orderkey", "l_partkey", "l_suppkey", days("l_shipdate").alias("day"))
    li = li.join(what, F.col("l_partkey") == F.col("p_partkey")).select("l_orderkey", "l_suppkey", "day", "kind")
    li = li.join(where, F.col("l_suppkey") == F.col("s_suppkey")).select("l_orderkey", "day", "kind", "place")
    li = li.join(orders.select("o_orderkey", seq.alias("seq_id")), F.col("l_orderkey") == F.col("o_orderkey"))
    li = li.select("seq_id", F.col("day").cast("long").alias("txn_key"), F.lit("L").alias("type"), F.array("kind", "place").alias("concepts"))
    return build_plain(o.unionByName(li), ORDER_TREES)


LENGTHS = "Any(short(s0,s1),long(l0,l1))"


def dialogues(spark: SparkSession, directory: str) -> Corpus:
    """Conversations: every turn a transaction, three types, length buckets."""
    turns = read_table(spark, directory, "conversations")
    n = F.length("text")
    bucket = F.when(n < 100, "short/s0").when(n < 300, "short/s1").when(n < 1000, "long/l0").otherwise("long/l1")
    rows = turns.select(F.col("conv_id").cast("string").alias("seq_id"), F.col("turn").alias("txn_key"), F.col("role").alias("type"), F.array(F.coalesce(bucket, F.lit(""))).alias("concepts"), F.struct(n.alias("n"), F.coalesce(bucket, F.lit("")).alias("bucket"), F.col("turn").cast("int").alias("day")).alias("attrs"), F.col("turn").alias("event_id"))
    roles = ["assistant", "system", "user"]
    relations = []
    for i, a in enumerate(roles):
        for b in roles[i:]:
            relations.append(Relation(a, b, *(rel.identity("bucket") if a == b else rel.compare("n", ("Longer", "Same", "Shorter")))))
    return build(rows, {r: ["length"] for r in roles}, relations)


def sources(spark: SparkSession, directory: str) -> Corpus:
    """Documents by source, five to a transaction, with labels where there are any."""
    docs = read_table(spark, directory, "documents").select("doc_id", "source", "lang")
    labels = read_table(spark, directory, "labels")
    family = F.when(F.col("lang").isin("fr", "es"), "Romance").otherwise("Germanic")
    place = F.expr("cast((row_number() over (partition by source order by doc_id) - 1) div 5 as long)")
    rows = docs.join(labels, "doc_id", "left").withColumn("txn_key", place)
    graded = lambda c: F.coalesce(F.concat(F.lit(c), F.col(c).cast("string")), F.lit(""))
    rows = rows.select(F.col("source").alias("seq_id"), "txn_key", F.lit("D").alias("type"), F.array(F.concat_ws("/", family, "lang"), graded("quality"), graded("toxic")).alias("concepts"), F.struct("lang", F.col("txn_key").cast("int").alias("day")).alias("attrs"), F.col("doc_id").alias("event_id"))
    return build(rows, {"D": ["lang", "quality", "toxic"]}, [Relation("D", "D", *rel.identity("lang"))], distinct=False)


def vectors(spark: SparkSession, directory: str) -> Corpus:
    """Embeddings ten to a sequence; the relation is computed from the vectors."""
    e = read_table(spark, directory, "embeddings").where("embedding is not null and label is not null")
    rows = e.select(F.expr("cast(vec_id div 10 as string)").alias("seq_id"), F.col("vec_id").alias("txn_key"), F.when(F.col("label") % 2 == 0, "even").otherwise("odd").alias("type"), F.array(F.concat(F.lit("c"), F.col("label").cast("string"))).alias("concepts"), F.struct(F.col("embedding").alias("v"), F.lit(0).alias("day")).alias("attrs"), F.col("vec_id").alias("event_id"))
    pairs = [("even", "even"), ("even", "odd"), ("odd", "odd")]
    return build(rows, {"even": ["label"], "odd": ["label"]}, [Relation(a, b, *rel.cosine("v", 0.8, 0.3)) for a, b in pairs])


def web(spark: SparkSession, directory: str) -> Corpus:
    """Pages by host under the tree of their paths."""
    pages = read_table(spark, directory, "pages").where("url is not null")
    path = F.regexp_extract("url", r"^\w+://[^/]+/([^?#]*)", 1)
    path = F.array_join(F.filter(F.split(path, "/"), lambda x: x != ""), "/")
    first = F.regexp_extract("url", r"^\w+://[^/]+/([^/?#]*)", 1)
    rows = pages.select(F.regexp_extract("url", r"^\w+://([^/]+)", 1).alias("seq_id"), F.col("page_id").alias("txn_key"), F.when(F.startswith("url", F.lit("https")), "https").otherwise("http").alias("type"), F.array(path).alias("concepts"), F.struct(first.alias("first"), F.lit(0).alias("day")).alias("attrs"), F.col("page_id").alias("event_id"))
    pairs = [("http", "http"), ("http", "https"), ("https", "https")]
    return build(rows, {"http": ["path"], "https": ["path"]}, [Relation(a, b, *rel.identity("first")) for a, b in pairs])
