"""Phrase counts over event streams: keyed state, windows, late data. Each stream ends in a Parquet folder."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from phraseloom.functions import kernels as k
from phraseloom.functions import transition as t
from phraseloom.operators.changes import edit_rows
from phraseloom.operators.per_string import flat_map
from phraseloom.plans.folders import shared_folder
from phraseloom.sources.tables import part_names


def event_stream(spark: SparkSession, sf_dir: str, table: str = "events") -> DataFrame:
    """The table's files as a stream, with the table's own schema."""
    schema = spark.read.parquet(f"{sf_dir}/{table}.parquet").schema
    rows = spark.readStream.schema(schema).option("pathGlobFilter", f"{table}.parquet").parquet(sf_dir)
    return rows.withColumn("ts", F.col("ts").cast("timestamp"))


def _finish(spark: SparkSession, stream: DataFrame, mode: str, keys: list[str]) -> DataFrame:
    """Run the stream over what is there, and return the last state of each key."""
    folder = f"{shared_folder(spark)}/stream-{uuid.uuid4().hex}"

    def put(batch: DataFrame, number: int) -> None:
        batch.withColumn("_batch", F.lit(number)).write.mode("overwrite").parquet(f"{folder}/out/batch={number}")  # idempotent by batch

    stream.writeStream.outputMode(mode).foreachBatch(put).option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start().awaitTermination()
    rows = spark.read.parquet(f"{folder}/out/batch=*")
    fields = [c for c in rows.columns if c not in (*keys, "_batch")]
    if not keys:
        return rows.drop("_batch")
    return rows.groupBy(*keys).agg(F.max_by(F.struct(*fields), "_batch").alias("_s")).select(*keys, "_s.*")


def sliding_counts(spark: SparkSession, sf_dir: str, size: int = 16, delay: str = "30 days") -> DataFrame:
    """Phrases of each user's last ``size`` events after every event of the table."""
    return sliding_counts_of(event_stream(spark, sf_dir), size, delay)


def sliding_counts_of(events: DataFrame, size: int = 16, delay: str = "30 days") -> DataFrame:
    """Phrases of each user's last ``size`` events after every event of a stream, in the order of time.

    An event up to ``delay`` late, in whatever batch it comes, takes its place among the events already seen, and the counts
    from there on are given anew; the last ones of each ordinal stand. Later events and copies are dropped. State holds the
    events that the watermark has not passed, and the ``size`` before them.
    """
    known = events.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])
    symbols = known.select("user_id", "ts", F.unix_micros("ts").alias("us"), "event_id", F.substring("event_type", 1, 1).alias("sym"))

    def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        tail, seen, times, ids, syms = state.get if state.exists else ("", 0, [], [], [])
        rows = pd.concat(list(frames))
        held = list(zip(times, ids, syms, strict=True))
        new = list(zip(rows["us"].tolist(), rows["event_id"].tolist(), rows["sym"], strict=True))
        first = min(new)
        merged = sorted(held + new)
        out, text = [], tail
        for place, entry in enumerate(merged):
            text = (text + entry[2])[-size:]
            if entry >= first:
                out.append((key[0], seen + place + 1, len(text), sum(1 for _ in k.parse(text))))
        passed = sum(1 for e in merged if e[0] < state.getCurrentWatermarkMs() * 1000)
        tail, seen = (tail + "".join(e[2] for e in merged[:passed]))[-size:], seen + passed
        state.update((tail, seen, *([e[c] for e in merged[passed:]] for c in range(3))))
        yield pd.DataFrame(out, columns=["sid", "ord", "n", "phrases"])

    held = "tail string, seen long, times array<long>, ids array<long>, syms array<string>"
    kept = symbols.groupBy("user_id").applyInPandasWithState(step, "sid long, ord long, n long, phrases long", held, "append", GroupStateTimeout.NoTimeout)
    return _finish(events.sparkSession, kept, "append", ["sid", "ord"])


def replay_edits(edits: DataFrame, bodies: DataFrame) -> DataFrame:
    """Keyed state holds each string with its reach forest; every edit ``(sid, seq, op, pos, sym)`` costs one transition.

    ``edits`` may be a stream; ``bodies`` (static) gives a string's first version. The edits of a string are numbered from 1
    on. An edit that comes before an earlier-numbered one waits in the state until that has come, in whatever batch;
    repeated numbers are ignored.
    """
    fields = ["seq", "op", "pos", "sym"]

    def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        rows = pd.concat(list(frames))
        if state.exists:
            body, parents, last, *held = state.get
            parents = list(parents)
        else:
            body, last, held = rows["body"].iloc[0], 0, [[]] * 4
            parents = t.parents_of(body)
        waiting = {e[0]: e for e in [*zip(*held, strict=True), *rows[fields].itertuples(index=False, name=None)] if e[0] > last}
        out = []
        while last + 1 in waiting:
            last, op, pos, sym = waiting.pop(last + 1)
            body, parents, _ = t.transition(body, op, pos, sym, None, parents)
            out.append((key[0], last, len(body), t.phrase_count(parents)))
        kept = sorted(waiting.values())
        state.update((body, parents, int(last), *([e[c] for e in kept] for c in range(4))))
        yield pd.DataFrame(out, columns=["sid", "seq", "n", "phrases"])

    joined = edits.join(bodies, "sid")
    held = "body string, parents array<long>, last long, seqs array<long>, ops array<string>, places array<long>, syms array<string>"
    return joined.groupBy("sid").applyInPandasWithState(step, "sid long, seq long, n long, phrases long", held, "append", GroupStateTimeout.NoTimeout)


def edit_counts(spark: SparkSession, sf_dir: str, kinds: tuple[str, ...]) -> DataFrame:
    """``replay_edits`` on three edits of every part name, the part table read as a stream."""
    schema = spark.read.parquet(f"{sf_dir}/part.parquet").schema
    parts = spark.readStream.schema(schema).option("pathGlobFilter", "part.parquet").parquet(sf_dir)
    edits = edit_rows(parts.select(F.col("p_partkey").alias("sid"), F.col("p_name").alias("body")), 3, kinds).drop("body")
    return _finish(spark, replay_edits(edits, part_names(spark, sf_dir)), "append", ["sid", "seq"])


def followed_by(spark: SparkSession, sf_dir: str, first: str, then: str, within: str, delay: str = "30 days") -> DataFrame:
    """Pairs of event ids: each ``first`` with every ``then`` of the same user at most ``within`` later; both watermarks and the span bound the state."""
    events = event_stream(spark, sf_dir).withWatermark("ts", delay)
    a = events.where(F.col("event_type") == first).select(F.col("user_id").alias("u"), F.col("ts").alias("began"), F.col("event_id").alias(f"{first}_id"))
    b = events.where(F.col("event_type") == then).select("user_id", "ts", F.col("event_id").alias(f"{then}_id"))
    near = (F.col("u") == F.col("user_id")) & (F.col("ts") >= F.col("began")) & (F.col("ts") <= F.col("began") + F.expr(f"INTERVAL {within}"))
    return _finish(spark, a.join(b, near).select(f"{first}_id", f"{then}_id"), "append", [])


def windowed_strings(events: DataFrame, window) -> DataFrame:
    """``(user_id, start, body)``: the ordered string of each user's window."""
    entry = F.struct("ts", "event_id", F.substring("event_type", 1, 1).alias("sym"))
    body = F.array_join(F.transform(F.array_sort(F.collect_list(entry)), lambda e: e["sym"]), "")
    return events.groupBy("user_id", window.alias("w")).agg(body.alias("body")).select("user_id", F.col("w.start").alias("start"), "body")


def window_counts(spark: SparkSession, sf_dir: str, kind: str = "tumbling", delay: str = "30 days") -> DataFrame:
    """Phrases of each user's string per tumbling day, sliding two days, or session with gaps of at most a day."""
    window = {"tumbling": lambda: F.window("ts", "1 day"), "sliding": lambda: F.window("ts", "2 days", "1 day"), "session": lambda: F.session_window("ts", "1 day")}[kind]()
    strings = windowed_strings(event_stream(spark, sf_dir).withWatermark("ts", delay), window)
    # Session windows cannot report updates, so their strings come complete.
    finished = _finish(spark, strings, "complete" if kind == "session" else "update", ["user_id", "start"])
    counted = flat_map(finished.select("user_id", F.expr("timestampdiff(MICROSECOND, timestamp_ntz'1970-01-01', cast(start as timestamp_ntz))").alias("us"), "body"), lambda u, us, s: [(u, us, len(s), sum(1 for _ in k.parse(s)))], "user_id long, start_us long, n long, phrases long")
    return counted
