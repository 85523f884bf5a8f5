"""Sources and sinks."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition
from pyspark.sql.types import StructType

from relseq.functions import taxonomy
from relseq.operators.corpus import Corpus

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def read_table(spark: SparkSession, directory: str, name: str) -> DataFrame:
    if name not in TABLES:
        raise ValueError(f"no such table: {name}")
    return spark.read.parquet(f"{directory}/{name}.parquet")


def read_events(spark: SparkSession, path: str, kind: str, schema: str | StructType, **options) -> DataFrame:
    """Event logs as csv, json (lines), parquet or orc, always with a declared schema."""
    reader = spark.read.schema(schema).options(**options)
    if kind == "csv" and "header" not in options:
        reader = reader.option("header", True)
    return reader.format(kind).load(path)


def save_corpus(corpus: Corpus, path: str, partitions: int | None = None) -> None:
    """Packed rows dealt by sequence, so later levels read them without an exchange."""
    rows = corpus.sequences
    rows = rows.repartition(partitions, "seq_id") if partitions else rows
    rows.write.mode("overwrite").parquet(path)


def load_corpus(spark: SparkSession, path: str, like: Corpus) -> Corpus:
    return Corpus(spark.read.parquet(path), like.trees, like.relations, like.with_concepts)


def write_occurrences(occurrences: DataFrame, path: str) -> None:
    """Occurrences by skeleton: a level's memory can be given up once they are stored."""
    occurrences.write.mode("overwrite").partitionBy("skeleton").parquet(path)


def write_patterns(found: DataFrame, path: str, kind: str = "json") -> None:
    out = found.select(*[F.concat_ws("|", c).alias(c) if t.startswith("array") and kind == "csv" else F.col(c) for c, t in found.dtypes])
    out.write.mode("overwrite").option("header", True).format(kind).save(path)


def has_type(kind: str) -> Column:
    return F.exists("events", lambda e: e["type"] == kind)


def mentions(concept: str) -> Column:
    """Sequences with an event at or below a concept, in any tree."""
    return F.exists("events", lambda e: F.exists(e["concepts"], lambda c: taxonomy.under(c, concept)))


class TreePartition(InputPartition):
    pass


class PrefixTreeReader(DataSourceReader):
    def __init__(self, options) -> None:
        self.text, self.tax = options.get("text"), options.get("tax_id", "t")
        if not self.text:
            raise ValueError("give the tree as option 'text'")

    def read(self, partition) -> Iterator[tuple]:
        paths = ["", *taxonomy.parse_prefix_tree(self.text)]
        inner = {p.rpartition("/")[0] for p in paths if p}
        for p in paths:
            yield (self.tax, p, p.rpartition("/")[0] if p else None, p.count("/") + 1 if p else 0, p not in inner)


class PrefixTreeSource(DataSource):
    """``spark.read.format("prefix_tree").option("text", "Any(a(b,c),d)").load()``"""

    @classmethod
    def name(cls) -> str:
        return "prefix_tree"

    def schema(self) -> str:
        return taxonomy.NODE_SCHEMA

    def reader(self, schema) -> DataSourceReader:
        return PrefixTreeReader(self.options)
