"""Streaming forms over the events table: windowed counts, and an automaton that runs on for each user."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from walkengine.lang.automata import compile_pattern
from walkengine.operators.around import EVENT_TYPES
from walkengine.session import read_table, shared_dir, staged


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events table as a stream of its files, with a watermark; copies of an event within it are dropped."""
    schema = read_table(spark, sf_dir, "events").schema
    raw = spark.readStream.schema(schema).option("pathGlobFilter", "events.parquet").option("recursiveFileLookup", "false").parquet(sf_dir)
    return raw.withColumn("at", F.col("ts").cast("timestamp")).withWatermark("at", "1 hour").dropDuplicatesWithinWatermark(["event_id"])


def drain(stream: DataFrame, mode: str) -> DataFrame:
    """Runs the stream over what there is and returns what it wrote."""
    spark = stream.sparkSession
    name = f"drained_{uuid.uuid4().hex[:8]}"
    folder = f"{shared_dir(spark)}/stream-{name}"
    parts: list[DataFrame] = []

    def keep(batch: DataFrame, number: int) -> None:
        out = staged(batch, f"stream-{number}")
        if mode == "complete":
            parts.clear()
        parts.append(out)

    stream.writeStream.foreachBatch(keep).outputMode(mode).option("checkpointLocation", folder).trigger(availableNow=True).start().awaitTermination()
    out = parts[0]
    for x in parts[1:]:
        out = out.unionByName(x)
    return out


def stream_hourly_labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    counts = event_stream(spark, sf_dir).groupBy(F.window("at", "1 hour").alias("w"), "event_type").agg(F.count("*").alias("n"))
    return drain(counts, "complete").select(F.unix_seconds("w.start").alias("start"), "event_type", "n")


def stream_user_automaton(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Users whose events so far contain view click+ purchase; the state is one set of automaton states for each user."""
    nfa = compile_pattern(".* view click+ purchase .*", EVENT_TYPES)

    def advance(key: tuple, rows: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        now = frozenset(q for q in range(nfa.n) if state.get[0] >> q & 1) if state.exists else nfa.initial
        was = bool(now & nfa.final) and state.exists
        events = pd.concat(list(rows)).sort_values(["ts", "event_id"])
        for kind in events["event_type"]:
            now = nfa.step(now, {kind})
        state.update((nfa.mask(now),))
        if now & nfa.final and not was:
            yield pd.DataFrame({"user_id": [key[0]]})

    grouped = event_stream(spark, sf_dir).groupBy("user_id")
    return drain(grouped.applyInPandasWithState(advance, "user_id long", "states long", "append", GroupStateTimeout.NoTimeout), "append")


QUERIES = {f.__name__: f for f in (stream_hourly_labels, stream_user_automaton)}
ORACLES = {
    "stream_hourly_labels": "SELECT floor(epoch(ts) / 3600)::BIGINT * 3600 AS start, event_type, count(*) AS n FROM events GROUP BY ALL",
    "stream_user_automaton": "SELECT user_id FROM events GROUP BY user_id HAVING regexp_matches(string_agg(left(event_type, 1), '' ORDER BY ts, event_id), 'vc+p')",
}
