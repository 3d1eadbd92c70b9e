"""Structured Streaming operators: scans of arriving text, windows of hits, joins with truth, patterns that span rows, incremental models.

Event times are TIMESTAMP (cast from TIMESTAMP_NTZ, which watermarks refuse). Results equal the batch twins in patternlm.queries.events.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from patternlm.functions import automata as fa
from patternlm.operators.model import fit_ngram, merge_counts
from patternlm.sources.io import INSULTS, with_hits


def read_files(spark: SparkSession, path: str, schema, per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", per_trigger).parquet(path)


def event_time(events: DataFrame, late: str = "1 hour", col: str = "ts") -> DataFrame:
    return events.withColumn(col, F.col(col).cast("timestamp")).withWatermark(col, late)


def scan(docs: DataFrame, words: tuple[str, ...] = INSULTS, col: str = "text") -> DataFrame:
    """Stateless: arriving texts that hold a listed word, with hit and prompt."""
    return with_hits(docs, col, words)


def window_counts(events: DataFrame, width: str, slide: str | None = None, by: str = "event_type") -> DataFrame:
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    return events.groupBy(w.alias("w"), by).agg(F.count("*").alias("n")).select(F.unix_seconds("w.start").alias("start_s"), by, "n")


def session_counts(events: DataFrame, gap: str) -> DataFrame:
    g = events.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n"))
    return g.select("user_id", F.unix_micros("w.start").alias("start_us"), "n")


def distinct_hits(events: DataFrame, keys: list[str]) -> DataFrame:
    """First sightings only, with state bounded by the watermark."""
    return events.dropDuplicatesWithinWatermark(keys)


def against_truth(hits: DataFrame, truth: DataFrame, on: str) -> DataFrame:
    """Stream-static: hits that a table knows."""
    return hits.join(truth.select(on).distinct(), on, "left_semi")


def followed_by(events: DataFrame, first: str, then: str, within: str = "1 hour") -> DataFrame:
    """Stream-stream: an event of one type followed by another of the same user within a bound (events carry their watermark)."""
    a = events.where(F.col("event_type") == first).select(F.col("event_id").alias("first_id"), "user_id", F.col("ts").alias("t0"))
    b = events.where(F.col("event_type") == then).select(F.col("event_id").alias("then_id"), F.col("user_id").alias("u1"), F.col("ts").alias("t1"))
    return a.join(b, (F.col("user_id") == F.col("u1")) & (F.col("t1") >= F.col("t0")) & (F.col("t1") <= F.col("t0") + F.expr(f"INTERVAL {within}"))).select("first_id", "then_id")


def spanning_pattern(events: DataFrame, pattern: str, letters: dict[str, str], key: str = "user_id") -> DataFrame:
    """Matches of a pattern over the sequence of a key's event types, one letter each: the automaton's states are the key's state.

    Emits (key, event_id) of events at which a match ends. The automaton starts anew at every event, so matches may begin anywhere. Rows of a
    micro-batch are ordered by time.
    """
    dfa = fa.compile_regex(pattern)

    def run(k: tuple, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        live = set(state.get[0]) if state.exists else set()
        rows = pd.concat(list(frames)).sort_values(["ts", "event_id"])
        out = []
        for kind, event_id in zip(rows["event_type"], rows["event_id"], strict=True):
            c = letters.get(kind)
            live = {t for s in live | {0} if (t := dfa.edges[s].get(c)) is not None}
            if live & set(dfa.finals):
                out.append((k[0], event_id))
        state.update((sorted(live),))
        yield pd.DataFrame(out, columns=[key, "event_id"])

    return events.groupBy(key).applyInPandasWithState(run, f"{key} long, event_id long", "live array<int>", "append", "NoTimeout")


def update_counts(store: str, order: int) -> Callable[[DataFrame, int], None]:
    """foreachBatch: merge a micro-batch of token arrays into a store of counts, one folder a batch (replays overwrite their own)."""

    def merge(batch: DataFrame, batch_id: int) -> None:
        spark = batch.sparkSession
        new = fit_ngram(batch, "tokens", order)
        if batch_id:
            new = merge_counts(spark.read.parquet(f"{store}/{batch_id - 1}"), new)
        new.write.mode("overwrite").parquet(f"{store}/{batch_id}")

    return merge


def sample_forever(spark: SparkSession, draw: Callable[[DataFrame], DataFrame], sink: str, rows_per_second: int = 10):
    """Infinite sampling: the rate source numbers samples, draw turns numbers into samples, batches append to sink."""
    rate = spark.readStream.format("rate").option("rowsPerSecond", rows_per_second).load().select(F.col("value").alias("id"))
    return rate.writeStream.foreachBatch(lambda batch, _: draw(batch).write.mode("append").parquet(sink))


def run_to_end(stream: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """All available input through a memory sink."""
    q = stream.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    return stream.sparkSession.table(name)
