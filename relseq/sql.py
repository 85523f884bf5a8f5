"""The SQL surface: table functions for ``LATERAL`` and scalar functions.

After ``register(spark)``::

    SELECT s.seq_id, o.positions FROM seq s, LATERAL occurrences(s.types, s.txns, 'A ; F', 3, NULL) o
    SELECT t.ancestor FROM LATERAL ancestors('a/b/c') t
"""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from relseq.functions import taxonomy
from relseq.operators import matching, patterns
from relseq.sources.tables import PrefixTreeSource


@udtf(returnType="positions array<int>, steps int")
class Occurrences:
    """Index vectors of a skeleton in one sequence given as types and transactions."""

    def eval(self, types, txns, skeleton: str, max_gap: int | None, max_span: int | None) -> Iterator[tuple]:
        if types is None or txns is None or skeleton is None:
            return
        found, steps, _ = matching.search_one(list(types), list(txns), list(range(1, len(types) + 1)), patterns.parse(skeleton), max_gap, max_span, True)
        for f in found:
            yield f, steps


@udtf(returnType="ancestor string, depth int")
class Ancestors:
    """A concept and what lies above it, deepest first, the root left out."""

    def eval(self, concept: str) -> Iterator[tuple]:
        for c in taxonomy.climb(concept or ""):
            yield c, c.count("/") + 1


def register(spark: SparkSession) -> None:
    spark.udtf.register("occurrences", Occurrences)
    spark.udtf.register("ancestors", Ancestors)
    spark.dataSource.register(PrefixTreeSource)
