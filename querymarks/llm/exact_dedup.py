"""Exact duplicates by progressive refinement: length, prefix hash, then the full hash."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Workspace, ascii_lower, drop_rows, fresh, id_text, table, text_hash


def refine(docs: DataFrame, ws: Workspace, id_col: str = "doc_id", text_col: str = "text", prefix_chars: int = 64) -> DataFrame:
    """Per document: doc_id, th (text hash), octets, survived, digest (binary SHA-256 of the normalised text).

    One scan says of each text its byte length, the hash of its first ``prefix_chars`` characters and the full hash,
    which its reader reports for every row; no text leaves its task. Rows are grouped by length and prefix hash, where
    the map side combines, so that a group of copies sends one row per task. Only documents of groups with two rows or
    more survive into the grouping by full hash. Null texts are empty texts. Repeated rows stay rows of their own.
    """
    text = F.col("text")
    hashes = (F.xxhash64("text").alias("th"), F.octet_length("text").alias("octets"), F.xxhash64(ascii_lower(F.substring("text", 1, prefix_chars))).alias("prefix"))
    base = ws.save(id_text(docs, id_col, text_col).select("doc_id", *hashes, F.unhex(F.sha2(ascii_lower(text), 256)).alias("digest")), "hashes")
    alike = base.groupBy("octets", "prefix").agg(F.count(F.lit(1)).alias("n")).where("n > 1")
    # Keyed apart from the grouping, so that both sides are dealt anew and a hot key's rows can be split over tasks.
    alike = alike.select((F.col("octets") + 1).alias("key"), "prefix", F.lit(True).alias("survived"))
    joined = base.withColumn("key", F.col("octets") + 1).join(alike, ["key", "prefix"], "left")
    return ws.save(joined.select("doc_id", "th", "octets", F.coalesce("survived", F.lit(False)).alias("survived"), "digest"), "refined")


def exact_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", ws: Workspace | None = None) -> DataFrame:
    """Per document: doc_id, keep_id, group_size, kept, digest, th.

    Texts are equal when identical after lower-casing A-Z. The row with the largest doc_id stays; rows that
    repeat it (same id, equal text) are the same document and are marked kept alike. A null doc_id stays only
    where its group has no other. An empty table gives an empty result.
    """
    ws = ws or Workspace(docs.sparkSession, "exact")
    full = refine(docs, ws, id_col, text_col)
    alone = full.where("not survived").select("doc_id", F.col("doc_id").alias("keep_id"), F.lit(1).cast("long").alias("group_size"), F.lit(True).alias("kept"), "digest", "th")
    groups = full.where("survived").groupBy("octets", "digest").agg(F.max("doc_id").alias("keep_id"), F.count(F.lit(1)).alias("group_size"))
    # As above, keyed apart from the grouping, so that the rows of one large group split over tasks.
    groups = groups.select((F.col("octets") + 1).alias("key"), "digest", "keep_id", "group_size")
    alike = full.where("survived").withColumn("key", F.col("octets") + 1).join(groups, ["key", "digest"])
    alike = alike.select("doc_id", "keep_id", "group_size", F.col("doc_id").eqNullSafe(F.col("keep_id")).alias("kept"), "digest", "th")
    return alike.unionByName(alone)


def drop_copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of ``docs`` that exact_groups() keeps, with all their columns; repeated rows go too.

    Of each text one row stays, whatever ids other texts have: copies are joined away by id and text hash, where
    null equals null. Rows that repeat the one that stays differ from it at most in the case of letters and in further
    columns; the one with the least text hash stays, and of those alike in that any.
    """
    ws = Workspace(docs.sparkSession, "exact")
    groups = ws.save(exact_groups(docs, id_col, text_col, ws), "groups")
    again = groups.where("kept and group_size > 1").groupBy("doc_id", "digest").agg(F.count(F.lit(1)).alias("n"), F.min("th").alias("least")).where("n > 1")
    again = ws.save(again, "again")
    same = groups["doc_id"].eqNullSafe(again["doc_id"]) & (groups["digest"] == again["digest"])
    other_case = groups.join(again, same & (groups["th"] != again["least"]), "left_semi").select("doc_id", "th")
    kept = drop_rows(docs, groups.where("not kept").select("doc_id", "th").unionByName(other_case), ws, id_col, text_col)
    twice = groups.where("kept").groupBy("doc_id", "th").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("doc_id", "th")
    if twice.isEmpty():
        return kept
    # Only repeated rows meet: the others stay where they are.
    twice = ws.save(twice, "twice")
    met = kept[id_col].cast("long").eqNullSafe(twice["doc_id"]) & (text_hash(kept[text_col]) == twice["th"])
    known = twice.hint("shuffle_hash")
    th = fresh(docs, "th")
    once = kept.join(known, met, "left_semi").withColumn(th, text_hash(kept[text_col])).dropDuplicates([id_col, th]).drop(th)
    return kept.join(known, met, "left_anti").unionByName(once)


def op9_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """exact_groups() of ``documents``: a row for each of its rows, null texts as empty ones."""
    out = exact_groups(table(spark, sf_dir, "documents"))
    return out.select("doc_id", "keep_id", "group_size", "kept", F.lower(F.hex("digest")).alias("text_sha256"))


OP9_SQL = """
WITH t AS (SELECT doc_id, translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS norm FROM documents)
SELECT doc_id, max(doc_id) OVER (PARTITION BY norm) AS keep_id, count(*) OVER (PARTITION BY norm) AS group_size,
       doc_id = max(doc_id) OVER (PARTITION BY norm) AS kept, sha256(norm) AS text_sha256
FROM t
"""
