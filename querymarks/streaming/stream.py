"""Submissions as a stream: windows, deduplication, best marks so far, and graded feedback."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from typing import Any

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout
from pyspark.sql.types import StringType, StructField, StructType

from ..operators import grade as grading

#: Texts whose canonical form a task of matched() keeps.
KNOWN_TEXTS = 20_000
SUBMISSIONS = "sub_id long, student_id long, question int, ts timestamp, mask int, style int, sql string"


def write_ordered(subs: DataFrame, path: str, files: int = 4) -> None:
    """Submissions as parquet files in the order of their time, for a stream to read one after the other."""
    subs.repartitionByRange(files, "ts").sortWithinPartitions("ts").write.mode("overwrite").parquet(path)


def submission_stream(spark: SparkSession, path: str, files_a_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(SUBMISSIONS).option("maxFilesPerTrigger", files_a_trigger).parquet(path)


def tumbling(subs: DataFrame, delay: str = "1 hour", every: str = "1 day") -> DataFrame:
    """question, start, attempts per window; rows behind the watermark are dropped."""
    return subs.withWatermark("ts", delay).groupBy(F.window("ts", every).alias("w"), "question").agg(F.count(F.lit(1)).alias("attempts")).select("question", F.col("w.start").alias("start"), "attempts")


def sliding(subs: DataFrame, delay: str = "1 hour", length: str = "1 day", every: str = "6 hours") -> DataFrame:
    return subs.withWatermark("ts", delay).groupBy(F.window("ts", length, every).alias("w"), "question").agg(F.count(F.lit(1)).alias("attempts")).select("question", F.col("w.start").alias("start"), "attempts")


def sessions(subs: DataFrame, delay: str = "1 hour", gap: str = "30 minutes") -> DataFrame:
    return subs.withWatermark("ts", delay).groupBy(F.session_window("ts", gap).alias("w"), "student_id").agg(F.count(F.lit(1)).alias("attempts")).select("student_id", F.col("w.start").alias("start"), "attempts")


def without_resubmits(subs: DataFrame, delay: str = "1 hour") -> DataFrame:
    """The first of equal texts of a student for a question within the watermark's delay."""
    return subs.withColumn("text_hash", F.xxhash64("sql")).withWatermark("ts", delay).dropDuplicatesWithinWatermark(["student_id", "question", "text_hash"]).drop("text_hash")


def best_so_far(marked: DataFrame, idle: str | None = None) -> DataFrame:
    """student_id, question, attempts, best after each batch, from rows with marks. With ``idle`` the rows need a
    watermark on ``ts``, and the state of a student goes once the watermark is that far past the last attempt."""

    def update(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        attempts, best, last = state.get if state.exists else (0, 0.0, 0)
        for frame in frames:
            attempts += len(frame)
            best = max(best, float(frame["marks"].fillna(0.0).max()))
            if idle:
                last = max(last, int(frame["ts"].max().timestamp() * 1000))
        state.update((attempts, best, last))
        if idle:
            state.setTimeoutTimestamp(max(last + int(pd.Timedelta(idle).total_seconds() * 1000), state.getCurrentWatermarkMs() + 1))
        yield pd.DataFrame({"student_id": [key[0]], "question": [key[1]], "attempts": [attempts], "best": [best]})

    out = "student_id long, question int, attempts long, best double"
    timeout = GroupStateTimeout.EventTimeTimeout if idle else GroupStateTimeout.NoTimeout
    return marked.groupBy("student_id", "question").applyInPandasWithState(update, out, "attempts long, best double, last long", "update", timeout)


def feedback_sink(correct: DataFrame, path: str, catalog: Any = None) -> Callable[[DataFrame, int], None]:
    """For foreachBatch: grades a batch and writes its feedback below its number, so that a repeated batch replaces itself."""

    def write(batch: DataFrame, number: int) -> None:
        graded = grading.feedback(grading.grade(batch, correct, catalog=catalog))
        graded.select("sub_id", "question", "marks", "n_edits", "feedback").write.mode("overwrite").json(f"{path}/batch={number}")

    return write


def matched(subs: DataFrame, correct: DataFrame, catalog: Any = None) -> DataFrame:
    """subs with canonical_match, by a join of the stream with the canonical forms of the correct queries, which are
    checked to be few and sent to all tasks. No state: each row is judged as it comes, a text once in a task as long as
    it is among the KNOWN_TEXTS met last."""
    rows = grading.collect_correct(correct)
    known = correct.sparkSession.createDataFrame([(q, s) for q, _, s in rows], "question int, sql string")
    truths = grading.with_forms(known, catalog).where("parse_error is null").select("question", "canonical_sql").distinct().collect()
    static = correct.sparkSession.createDataFrame(truths, "question int, canonical_sql string").withColumn("canonical_match", F.lit(True))

    def forms(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        known: dict[str | None, str | None] = {}
        for frame in frames:
            for x in frame["sql"].unique():
                if x not in known:
                    if len(known) >= KNOWN_TEXTS:
                        del known[next(iter(known))]
                    known[x] = grading.canonical_or_none(x, catalog)
            yield frame.assign(canonical_sql=[known[x] if x in known else grading.canonical_or_none(x, catalog) for x in frame["sql"]])

    judged = subs.mapInPandas(forms, StructType([*subs.schema.fields, StructField("canonical_sql", StringType())]))
    joined = judged.join(F.broadcast(static), ["question", "canonical_sql"], "left")
    return joined.withColumn("canonical_match", F.coalesce("canonical_match", F.lit(False))).drop("canonical_sql")


def run_to_end(stream: DataFrame, name: str, mode: str, checkpoint: str, dropped: list[int] | None = None) -> DataFrame:
    """All that is there. In append mode the rows go to Parquet files beside the checkpoint, so that the driver holds
    none of them; in the other modes to a table in memory, for results of bounded size. ``dropped`` receives how many
    late rows each batch left out."""
    spark, rows = stream.sparkSession, f"{checkpoint.rstrip('/')}-rows"
    writer = stream.writeStream.queryName(name).outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True)
    query = writer.format("parquet").option("path", rows).start() if mode == "append" else writer.format("memory").start()
    if not query.awaitTermination(600):
        query.stop()
        raise TimeoutError("the stream did not end")
    if dropped is not None:
        dropped += [int(op["numRowsDroppedByWatermark"]) for p in query.recentProgress for op in p["stateOperators"]]
    return spark.read.schema(stream.schema).parquet(rows) if mode == "append" else spark.table(name)
