"""Submissions from files, and graded results to files."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

SCHEMA = "sub_id long, student_id long, question int, ts timestamp, sql string"


def read_submissions(spark: SparkSession, path: str, kind: str = "parquet") -> DataFrame:
    """sub_id, student_id, question, ts, sql from parquet, json or csv (quoted, texts over several lines), with a fixed
    schema: no pass to infer one. Columns that a file lacks are null; rows that cannot be read keep their nulls."""
    reader = spark.read.schema(SCHEMA)
    if kind == "csv":
        return reader.option("header", True).option("multiLine", True).option("escape", '"').csv(path)
    return reader.json(path) if kind == "json" else reader.parquet(path)


def read_texts(spark: SparkSession, path: str, question: int) -> DataFrame:
    """A file for each submission: its name without the ending is the student's number."""
    files = spark.read.text(path, wholetext=True).select("value", F.col("_metadata.file_name").alias("file"))
    student = F.regexp_extract("file", r"(\d+)\.[^.]*$", 1)
    return files.select(F.xxhash64("file").alias("sub_id"), F.when(student != "", student.cast("long")).alias("student_id"), F.lit(question).alias("question"), F.lit(None).cast("timestamp").alias("ts"), F.col("value").alias("sql"))


def write_graded(graded: DataFrame, path: str, mode: str = "overwrite") -> None:
    """Parquet, a folder for each question; a question's rows are split over tasks by student."""
    graded.repartition("question", F.pmod(F.xxhash64("student_id"), F.lit(16))).write.mode(mode).partitionBy("question").parquet(path)


def write_feedback(graded: DataFrame, path: str, mode: str = "overwrite") -> None:
    graded.select("sub_id", "student_id", "question", "marks", "feedback").write.mode(mode).json(path)
