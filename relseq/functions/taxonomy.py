"""Taxonomies as path labels.

A concept is the path from below the root, its labels joined by ``/``; the root is the empty string. Paths in
byte order are in pre-order, an ancestor is a prefix that ends at a label, and no join is needed to climb.
``Dag`` holds rooted directed acyclic graphs, where a concept may have several parents.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

ROOT = ""
SEP = "/"
NODE_SCHEMA = "tax_id string, concept string, parent string, depth int, is_leaf boolean"


# -- driver-side, for declared trees ------------------------------------------------------------------------


def parse_prefix_tree(text: str) -> list[str]:
    """``Any(a(b,c),d)`` -> paths of all nodes but the root, in text order."""
    paths: list[str] = []
    stack: list[str] = []
    label, depth = "", 0

    def emit() -> None:
        nonlocal label
        name = label.strip()
        label = ""
        if not name:
            return
        if not depth:
            stack[:] = [ROOT]
        else:
            del stack[depth:]
            path = f"{stack[-1]}{SEP}{name}" if stack[-1] else name
            paths.append(path)
            stack.append(path)

    for ch in text:
        if ch in "(,)":
            emit()
            depth += {"(": 1, ",": 0, ")": -1}[ch]
            if depth < 0 or (ch == "," and depth == 0):
                raise ValueError("unbalanced tree text")
        else:
            label += ch
    emit()
    if depth:
        raise ValueError("unbalanced tree text")
    return paths


def render_prefix_tree(paths: list[str], root: str = "Any") -> str:
    children: dict[str, list[str]] = {}
    for p in paths:
        children.setdefault(p.rpartition(SEP)[0], []).append(p)

    def show(path: str, name: str) -> str:
        below = children.get(path, [])
        return name + (f"({','.join(show(c, c.rpartition(SEP)[2]) for c in below)})" if below else "")

    return show(ROOT, root)


def climb(path: str) -> list[str]:
    """The path and its ancestors below the root, deepest first."""
    labels = path.split(SEP) if path else []
    return [SEP.join(labels[:n]) for n in range(len(labels), 0, -1)]


def heap_path(n: int) -> str:
    """Path of node ``n`` in the binary heap whose root is 1: its binary digits after the first."""
    return SEP.join(bin(n)[3:])


# -- tables -------------------------------------------------------------------------------------------------


def from_paths(paths: DataFrame, column: str = "concept", tax_id: str = "t", sep: str = SEP) -> DataFrame:
    """Every node of the tree whose leaves or inner nodes ``paths`` names, the root included."""
    labels = F.filter(F.split(F.col(column), sep), lambda x: x != "")
    every = F.transform(F.sequence(F.lit(0), F.size(labels)), lambda n: F.array_join(F.slice(labels, 1, n), SEP))
    return nodes(paths.where(F.col(column).isNotNull()).select(F.explode(every).alias("concept")).distinct(), tax_id)


def nodes(concepts: DataFrame, tax_id: str) -> DataFrame:
    """Node table of distinct path labels (the root is added if missing)."""
    spark = concepts.sparkSession
    every = concepts.union(spark.range(1).select(F.lit(ROOT).alias("concept"))).distinct()
    rows = every.select(F.lit(tax_id).alias("tax_id"), "concept", parent(F.col("concept")).alias("parent"), depth(F.col("concept")).alias("depth"))
    inner = rows.where("concept <> ''").select(F.col("parent").alias("concept")).distinct().withColumn("inner", F.lit(True))
    return rows.join(inner, "concept", "left").select("tax_id", "concept", F.when(F.col("concept") != "", F.col("parent")).alias("parent"), "depth", F.col("inner").isNull().alias("is_leaf"))


def from_columns(df: DataFrame, columns: list[str], tax_id: str = "t") -> DataFrame:
    """A tree from hierarchy columns, the outermost first."""
    path = F.concat_ws(SEP, *[F.regexp_replace(F.col(c).cast("string"), SEP, "_") for c in columns])
    return from_paths(df.select(path.alias("concept")).distinct(), tax_id=tax_id)


def from_prefix_tree(spark: SparkSession, text: str, tax_id: str = "t") -> DataFrame:
    return nodes(spark.createDataFrame([(p,) for p in parse_prefix_tree(text)], "concept string"), tax_id)


def heap(spark: SparkSession, low: int, high: int, tax_id: str = "t") -> DataFrame:
    """Nodes ``low`` to ``high`` of the binary heap, and what lies above them."""
    return heap_of(spark.range(low, high + 1), "id", tax_id)


def heap_of(numbers: DataFrame, column: str, tax_id: str = "t") -> DataFrame:
    """The nodes of the binary heap with the numbers in a column, and what lies above them."""
    digits = F.bin(F.col(column))
    path = F.array_join(F.split(F.substring(digits, F.lit(2), F.length(digits)), ""), SEP)
    return from_paths(numbers.select(path.alias("concept")), tax_id=tax_id)


def from_edges(edges: DataFrame, child: str = "child", parent_col: str = "parent", tax_id: str = "t", most_levels: int = 64) -> DataFrame:
    """A tree from parent and child names; nodes without a parent hang below the root. Each round names one
    more level, so rounds are bounded by the depth."""
    e = edges.select(F.col(child).alias("child"), F.col(parent_col).alias("parent")).distinct()
    top = e.select(F.col("parent").alias("name")).distinct().join(e.select(F.col("child").alias("name")), "name", "left_anti")
    level = top.select("name", F.col("name").alias("concept"))
    found = level
    for _ in range(most_levels):
        level = e.join(level.withColumnRenamed("name", "parent"), "parent").select(F.col("child").alias("name"), F.concat_ws(SEP, "concept", "child").alias("concept"))
        if level.isEmpty():
            return nodes(found.select("concept").distinct(), tax_id)
        found = found.union(level)
    raise ValueError("the edges have a cycle or are deeper than most_levels")


def validate(edges: DataFrame, child: str = "child", parent_col: str = "parent") -> DataFrame:
    """(problem, name): children with several parents, roots beyond the first, and self-loops; empty if fine."""
    e = edges.select(F.col(child).alias("child"), F.col(parent_col).alias("parent")).distinct()
    several = e.groupBy("child").agg(F.count("*").alias("n")).where("n > 1").select(F.lit("several parents").alias("problem"), F.col("child").alias("name"))
    loops = e.where("child = parent").select(F.lit("own parent").alias("problem"), F.col("child").alias("name"))
    tops = e.select(F.col("parent").alias("name")).distinct().join(e.select(F.col("child").alias("name")), "name", "left_anti")
    more = tops.withColumn("n", F.count("*").over(Window.partitionBy())).where("n > 1").select(F.lit("several roots").alias("problem"), "name")
    return several.unionByName(loops).unionByName(more)


# -- columns ------------------------------------------------------------------------------------------------


def parent(concept: Column) -> Column:
    return F.when(F.instr(concept, SEP) > 0, F.regexp_replace(concept, "/[^/]*$", "")).otherwise(F.lit(ROOT))


def depth(concept: Column) -> Column:
    return F.when(concept == ROOT, F.lit(0)).otherwise(F.length(concept) - F.length(F.replace(concept, F.lit(SEP), F.lit(""))) + 1).cast("int")


def ancestors(concept: Column, include_root: bool = False) -> Column:
    """The concept and what lies above it, shallowest first; the root only if asked."""
    labels = F.filter(F.split(concept, SEP), lambda x: x != "")
    n = F.size(labels)
    upper = F.when(n > 0, F.transform(F.sequence(F.lit(1), F.greatest(n, F.lit(1))), lambda i: F.array_join(F.slice(labels, 1, i), SEP))).otherwise(F.array().cast("array<string>"))
    return F.concat(F.array(F.lit(ROOT)), upper) if include_root else upper


def subsumes(above: Column, below: Column) -> Column:
    """Is ``above`` the same as ``below`` or an ancestor of it?"""
    return (above == ROOT) | (above == below) | F.startswith(below, F.concat(above, F.lit(SEP)))


def subsumes_all(above: Column, below: Column) -> Column:
    """Slot by slot, for arrays of equal length."""
    return (F.size(above) == F.size(below)) & F.forall(F.zip_with(above, below, subsumes), lambda x: x)


def under(column: Column, concept: str) -> Column:
    """Filter for concepts at or below ``concept``; its prefix part reaches the scan."""
    return F.lit(True) if concept == ROOT else (column == concept) | F.startswith(column, F.lit(concept + SEP))


def deepest(concepts: Column) -> Column:
    """Of concepts on one path, the most specific; the root for none."""
    return F.coalesce(F.aggregate(concepts, F.lit(ROOT), lambda best, x: F.when(depth(x) > depth(best), x).otherwise(best)), F.lit(ROOT))


def common_ancestor(a: Column, b: Column) -> Column:
    """The nearest common ancestor of two paths."""
    return F.coalesce(F.element_at(F.array_intersect(ancestors(a, True), ancestors(b, True)), -1), F.lit(ROOT))


def order(taxonomy: DataFrame, kind: str = "pre") -> DataFrame:
    """Adds the rank in a depth-first walk, siblings by name: parents before (``pre``) or after children."""
    key = F.split("concept", SEP) if kind == "pre" else F.concat(F.concat_ws("\x01", F.split("concept", SEP)), F.lit("\x02"))
    if kind == "post":
        key = F.when(F.col("concept") == "", F.lit("\U0010ffff")).otherwise(F.concat(F.translate("concept", SEP, "\x01"), F.lit("\U0010ffff")))
    else:
        key = F.translate("concept", SEP, "\x01")
    return taxonomy.withColumn("rank", F.row_number().over(Window.partitionBy("tax_id").orderBy(key)))


def stats(taxonomy: DataFrame) -> DataFrame:
    """(tax_id, max_depth, min_depth, avg_depth, std_depth over leaves, leaves, nodes)."""
    leaf = F.when(F.col("is_leaf"), F.col("depth"))
    return taxonomy.groupBy("tax_id").agg(
        F.max(leaf).alias("max_depth"), F.min(leaf).alias("min_depth"), F.round(F.avg(leaf), 6).alias("avg_depth"), F.round(F.stddev_pop(leaf), 6).alias("std_depth"), F.count(leaf).alias("leaves"), F.count("*").alias("nodes")
    )


def closure(taxonomy: DataFrame, include_root: bool = True) -> DataFrame:
    """(concept, ancestor, distance), reflexive."""
    above = taxonomy.select("concept", F.explode(ancestors(F.col("concept"), include_root)).alias("ancestor"))
    return above.select("concept", "ancestor", (depth(F.col("concept")) - depth(F.col("ancestor"))).alias("distance"))


# -- rooted directed acyclic graphs ---------------------------------------------------------------------------


@dataclass
class Dag:
    """Concepts with several parents, small enough for the driver (a declared vocabulary)."""

    parents: dict[str, set[str]] = field(default_factory=dict)

    @classmethod
    def of(cls, edges: list[tuple[str, str]]) -> Dag:
        out = cls()
        for child, above in edges:
            out.parents.setdefault(child, set()).add(above)
            out.parents.setdefault(above, set())
        return out

    def above(self, concept: str) -> set[str]:
        """Reflexive ancestors."""
        seen, todo = {concept}, [concept]
        while todo:
            for p in self.parents.get(todo.pop(), ()):
                if p not in seen:
                    seen.add(p)
                    todo.append(p)
        return seen

    def most_specific(self, concepts: set[str]) -> set[str]:
        """The concepts that are not above another one of the set: a conjunction for one slot."""
        return {c for c in concepts if not any(c != d and c in self.above(d) for d in concepts)}

    def common_ancestor(self, concepts: set[str]) -> str:
        """The deepest concept above all of them; ties by name."""
        shared = set.intersection(*(self.above(c) for c in concepts))
        return max(sorted(shared), key=lambda c: len(self.above(c)))
