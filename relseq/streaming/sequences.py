"""Closing sequences over unbounded events, and skeleton support that follows the stream.

Events come in the long layout with an event time ``at``; the time column has to be a TIMESTAMP.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from relseq.operators import matching
from relseq.operators.corpus import Corpus, dedupe, pack


def with_time(events: DataFrame, column: str, delay: str = "1 day") -> DataFrame:
    """Adds the event time and its watermark; zone-less times are read as UTC wall time of the session."""
    return events.withColumn("at", F.col(column).cast("timestamp")).withWatermark("at", delay)


def _gather(grouped, key: Column) -> DataFrame:
    event = F.struct("txn_key", "type", "concepts", "event_id", "attrs")
    return grouped.agg(F.collect_list(event).alias("xs")).select(key.alias("seq_id"), "xs")


def close_sequences(events: DataFrame, length: str = "3 days", start: str = "1 day", slide: str | None = None) -> DataFrame:
    """(seq_id, xs): a user's events of one window, emitted once the watermark has passed its end. Windows are
    aligned to the epoch and moved by ``start``; with ``slide`` they overlap."""
    w = F.window("at", length, slide or length, start)
    grouped = events.groupBy(w.alias("w"), "user_id")
    return _gather(grouped, F.concat_ws("-", F.col("user_id").cast("string"), F.date_format("w.start", "yyyyMMdd")))


def follow(long: DataFrame) -> DataFrame:
    """Where the long layout already names its sequence: (seq_id, xs) of all events so far, each time an event of
    the sequence arrives (update mode)."""
    event = F.struct("txn_key", "type", "concepts", "event_id", "attrs")
    return long.groupBy("seq_id").agg(F.collect_list(event).alias("xs"))


def sessions(events: DataFrame, gap: str = "1 day") -> DataFrame:
    """The same with windows that end after ``gap`` without an event."""
    grouped = events.groupBy(F.session_window("at", gap).alias("w"), "user_id")
    return _gather(grouped, F.concat_ws("-", F.col("user_id").cast("string"), F.date_format("w.start", "yyyyMMddHHmmss")))


def without_replays(events: DataFrame) -> DataFrame:
    """Drops repeated event ids as long as the watermark allows to know them."""
    return events.dropDuplicatesWithinWatermark(["event_id"])


def late_rows(query) -> int:
    """Rows that came after the watermark had passed them and were dropped, over the progress still known."""
    return sum(int(op.get("numRowsDroppedByWatermark", 0)) for p in query.recentProgress for op in _plain(p).get("stateOperators", []))


def _plain(progress) -> dict:
    import json

    return progress if isinstance(progress, dict) else json.loads(progress.json)


def partial_matches(events: DataFrame, skeletons: list[list[str]], span_seconds: int) -> DataFrame:
    """(user_id, skeleton, event_ids) of all occurrences of type sequences inside ``span_seconds``, as they complete.

    ``events(user_id, event_id, type, at)`` with a watermark. The state of a user are the begun matches, which
    leave once no later event can complete them; a user without events for that long is forgotten. Events of one
    micro-batch are taken by time and id; across batches they have to come in that order.
    """

    def step(key, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        begun = [tuple(x) for x in state.get[0]] if state.exists else []
        rows = pd.concat(list(batches)).sort_values(["at", "event_id"])
        out: list[tuple[int, str, list[int]]] = []
        last = 0.0
        for kind, event, at in zip(rows["type"], rows["event_id"], rows["at"]):
            last = at.timestamp()
            begun = [b for b in begun if last - b[2] <= span_seconds]
            for i, done, first, ids in [*begun, *((i, 0, last, ()) for i in range(len(skeletons)))]:
                if skeletons[i][done] != kind:
                    continue
                ids = (*ids, int(event))
                if done + 1 == len(skeletons[i]):
                    out.append((key[0], " ; ".join(skeletons[i]), list(ids)))
                else:
                    begun.append((i, done + 1, first, ids))
        state.update(([(i, done, first, list(ids)) for i, done, first, ids in begun],))
        until = int((last + span_seconds) * 1000) + 1
        state.setTimeoutTimestamp(max(until, state.getCurrentWatermarkMs() + 1))
        yield pd.DataFrame(out, columns=["user_id", "skeleton", "event_ids"])

    begun = "array<struct<skeleton:int,done:int,first:double,ids:array<long>>>"
    return events.groupBy("user_id").applyInPandasWithState(step, "user_id long, skeleton string, event_ids array<long>", f"begun {begun}", "append", GroupStateTimeout.EventTimeTimeout)


def with_lookup(events: DataFrame, table: DataFrame, key: str) -> DataFrame:
    """A static table (a taxonomy, a relation's outcomes) at the side of the stream."""
    return events.join(table, key, "left")


def packed(closed: DataFrame, types: list[str]) -> DataFrame:
    """Closed sequences in the packed layout, equal events of a transaction once."""
    long = closed.select("seq_id", F.explode("xs").alias("x")).select("seq_id", "x.*")
    return pack(dedupe(long), types)


class Support:
    """Skeleton support over a stream of sequences. Each micro-batch stores the counts of the sequences it
    brought, under its own number, so a replayed batch overwrites itself and a sequence that grew counts as it
    last was."""

    def __init__(self, like: Corpus, skeletons: list[str], max_gap: int | None, path: str) -> None:
        self.like, self.skeletons, self.max_gap, self.path = like, skeletons, max_gap, path

    def __call__(self, batch: DataFrame, batch_id: int) -> None:
        rows = packed(batch, self.like.types)
        part = Corpus(rows, self.like.trees, self.like.relations)
        found = matching.occurrences(part, self.skeletons, self.max_gap).groupBy("seq_id", "skeleton").agg(F.count("*").alias("n"))
        found = found.groupBy("seq_id").agg(F.collect_list(F.struct("skeleton", "n")).alias("counts"))  # one entry a skeleton
        rows.select("seq_id").join(found, "seq_id", "left").write.mode("overwrite").parquet(f"{self.path}/batch={batch_id}")

    def total(self, spark) -> DataFrame:
        # Structs, because a sequence whose last state has no occurrence has null counts.
        last = spark.read.parquet(self.path).groupBy("seq_id").agg(F.max_by(F.struct("counts"), "batch").alias("x"))
        each = last.select(F.explode("x.counts").alias("c"))
        return each.groupBy("c.skeleton").agg(F.count("*").alias("support"), F.sum("c.n").alias("occurrences"))


def replay(spark, directory: str, name: str, schema) -> DataFrame:
    """A given table as a stream of files."""
    first = spark.read.parquet(f"{directory}/{name}.parquet").inputFiles()[0]
    folder, _, file = first.rpartition("/")
    reader = spark.readStream.schema(schema)
    return reader.parquet(folder) if folder.endswith(f"{name}.parquet") else reader.option("pathGlobFilter", file).parquet(folder)


def batch_counts(corpus: Corpus, skeletons: list[str], max_gap: int | None) -> DataFrame:
    rows = matching.occurrences(corpus, skeletons, max_gap)
    return rows.groupBy("skeleton").agg(F.count_distinct("seq_id").alias("support"), F.count("*").alias("occurrences"))

