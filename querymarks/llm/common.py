"""Helpers that the training-data operators share."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import Workspace

__all__ = ["LOWER", "UPPER", "Workspace", "ascii_lower", "drop_rows", "fresh", "id_remainder", "id_text", "table", "text_hash", "word_blocks"]
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def id_text(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Only the two columns an operator works on; a null text counts as empty."""
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))


def text_hash(text: Column | str = "text") -> Column:
    return F.xxhash64(F.coalesce(F.col(text) if isinstance(text, str) else text, F.lit("")))


def drop_rows(docs: DataFrame, gone: DataFrame, ws: Workspace, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``docs`` without the rows whose id (null equals null) and text hash stand in ``gone``: doc_id, th.

    The rows of ``gone`` form the hash tables and texts stream past, whatever their numbers; the hash also deals out rows
    without an id. Columns of ``docs`` may have any names.
    """
    gone = ws.save(gone.select(F.col("doc_id").alias("__gone"), F.col("th").alias("__th")).distinct(), "gone")
    return docs.join(gone.hint("shuffle_hash"), docs[id_col].cast("long").eqNullSafe(gone["__gone"]) & (text_hash(docs[text_col]) == gone["__th"]), "left_anti")


def fresh(df: DataFrame, name: str) -> str:
    """A column name that ``df`` does not have."""
    while name.lower() in (c.lower() for c in df.columns):
        name += "_"
    return name


def ascii_lower(text: Column) -> Column:
    """Lower-cases A-Z and nothing else; all-ASCII texts take the faster built-in."""
    return F.when(F.length(text) == F.octet_length(text), F.lower(text)).otherwise(F.translate(text, UPPER, LOWER))


def id_remainder(id_col: Column, modulus: int) -> Column:
    """crc32 of the id as text, modulo ``modulus``; a null id counts as the empty text."""
    return F.pmod(F.crc32(F.coalesce(id_col.cast("string"), F.lit(""))), F.lit(modulus))


def word_blocks(data: bytes, size: int = 1 << 20) -> Iterator[list[bytes]]:
    """The words of a text (runs of bytes other than 0x20 and 0x09-0x0D), a block of text at a time.

    Blocks end between words, so that a very long text never stands in memory as one list of words.
    """
    start, n = 0, len(data)
    while start < n:
        end = start + size
        if end >= n:
            yield data[start:].split()
            return
        while end < n and data[end] != 0x20 and not 0x09 <= data[end] <= 0x0D:
            end += 1
        yield data[start:end].split()
        start = end
