"""Repeated runs of lines: hashes of whole windows of lines, joined on their first place, deleted later."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Workspace, id_text, table

#: A repeated run goes if it has this many words or more.
LEAST_WORDS = 50
NO_ID = -(1 << 63)


def winnow(hashes: np.ndarray, words: np.ndarray, least_words: int = LEAST_WORDS) -> list[int]:
    """The places that hold the minimum of some window: the shortest stretch of lines from each line on with
    ``least_words`` words. A run of lines with so many words that stands in two texts contains a whole window,
    whose minimum (the last one of equals) is then selected in both. The operator does not thin its windows out so:
    a minimum that also stands elsewhere says too little about its run."""
    ends = np.searchsorted(np.cumsum(words), np.cumsum(words) - words + least_words)
    chosen, queue, head, right = set(), [], 0, 0
    for left, end in enumerate(ends.tolist()):
        if end >= len(hashes):
            break
        while right <= end:
            while len(queue) > head and hashes[queue[-1]] >= hashes[right]:
                queue.pop()
            queue.append(right)
            right += 1
        while queue[head] < left:
            head += 1
        chosen.add(queue[head])
    return sorted(chosen)


def windows(data: bytes, least_words: int = LEAST_WORDS) -> list[tuple[int, int, bytes]]:
    """(first line, last line, hash of all words by line) of the shortest stretches of lines with ``least_words`` words
    that begin at a line, and of those that end at a line and have two lines or more.

    Each two neighbours of a run with so many words, and each line of it, stand in one of these inside the run: those
    up to the end of the stretch from its first line in that one, later ones in the stretch that ends with them.
    """
    at, parts, counts = [], [], []
    for k, line in enumerate(data.lower().split(b"\n")):
        words = line.split()
        if words:
            at.append(k)
            parts.append(b" ".join(words))
            counts.append(len(words))
    sums = np.concatenate([[0], np.cumsum(counts, dtype=np.int64)])
    n = len(at)
    if sums[-1] < least_words:
        return []
    ends = np.searchsorted(sums, sums[:-1] + least_words)  # stretches [i, ends[i])
    starts = np.minimum(np.searchsorted(sums, sums[1:] - least_words, "right") - 1, np.arange(n) - 1)  # [starts[i], i + 1)
    spans = {(i, e) for i, e in enumerate(ends.tolist()) if e <= n} | {(i, e) for e, i in enumerate(starts.tolist(), 1) if i >= 0}
    places = np.concatenate([[0], np.cumsum([len(x) + 1 for x in parts])]).tolist()
    whole = memoryview(b"\n".join(parts))
    return [(at[i], at[e - 1], xxhash.xxh3_128_digest(whole[places[i] : places[e] - 1])) for i, e in spans]


def merged(ranges: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """The union of line ranges (both ends inclusive); those with a line in common become one."""
    out: list[tuple[int, int]] = []
    for a, b in sorted(ranges):
        if out and a <= out[-1][1]:
            out[-1] = (out[-1][0], max(b, out[-1][1]))
        else:
            out.append((a, b))
    return out


def repeated_runs(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", least_words: int = LEAST_WORDS) -> DataFrame:
    """doc_id, th (hash of the text), gone: array of (a, b), lines a to b of the text inclusive, counted from 0.

    A window goes where the same lines have an earlier place, by (doc_id, text hash, line). The windows that go make
    up all runs that stand before, whatever else their lines stand in: a passage in n texts makes n rows.
    """
    ws = Workspace(docs.sparkSession, "lines")

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            got = [windows(x.as_buffer().to_pybytes(), least_words) for x in batch.column(2)]
            owner = pa.array(np.repeat(np.arange(len(got)), [len(x) for x in got]))
            columns = list(zip(*(w for x in got for w in x))) or [()] * 3
            arrays = [batch.column(0).take(owner), batch.column(1).take(owner), *(pa.array(c, kind) for c, kind in zip(columns, (pa.int64(), pa.int64(), pa.binary())))]
            yield pa.RecordBatch.from_arrays(arrays, names=["doc_id", "th", "a", "b", "h"])

    def union(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            gone = [merged([(r["a"], r["b"]) for r in x]) for x in batch.column(2).to_pylist()]
            kind = pa.list_(pa.struct([("a", pa.int64()), ("b", pa.int64())]))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array([[{"a": a, "b": b} for a, b in x] for x in gone], kind)], names=["doc_id", "th", "gone"])

    prints = ws.save(_keyed(docs, id_col, text_col).mapInArrow(work, "doc_id long, th long, a long, b long, h binary"), "windows")
    # Saved, so that the join deals both sides anew and the places of a hot window can be split over tasks.
    first = ws.save(prints.groupBy("h").agg(F.min(F.struct("doc_id", "th", "a")).alias("f"), F.count(F.lit(1)).alias("n")).where("n > 1").select("h", "f"), "first")
    later = prints.join(first, "h").where("struct(doc_id, th, a) <> f").select("doc_id", "th", "a", "b")
    each = later.groupBy("doc_id", "th").agg(F.collect_set(F.struct("a", "b")).alias("met"))
    return ws.save(each.mapInArrow(union, "doc_id long, th long, gone array<struct<a: long, b: long>>"), "gone")


def _keyed(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    return id_text(docs, id_col, text_col).select(F.coalesce("doc_id", F.lit(NO_ID)).alias("doc_id"), F.xxhash64("text").alias("th"), "text")


def drop_repeated_runs(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", least_words: int = LEAST_WORDS) -> DataFrame:
    """Per row of ``docs``: doc_id, n_lines, n_removed, removed ("a-b" line ranges, comma-joined), text without them.

    A run of whole lines with ``least_words`` words or more that stands before, in a text with a smaller doc_id or
    further up in the same one, is deleted with the blank lines inside it; shorter ones stay. Lines are equal by
    their words, A-Z lower-cased. Repeated rows are one document and keep or lose the same lines. Null texts are
    empty, with one line. A text with everything repeated becomes empty and its row stays.
    """
    gone = repeated_runs(docs, id_col, text_col, least_words)
    joined = _keyed(docs, id_col, text_col).join(gone.hint("shuffle_hash"), ["doc_id", "th"], "left")
    lines = F.split("text", "\n", -1)
    out = lambda i: F.exists("gone", lambda r: (r["a"] <= i) & (i <= r["b"]))
    kept = F.when(F.col("gone").isNull(), F.col("text")).otherwise(F.array_join(F.filter(lines, lambda x, i: ~out(i)), "\n"))
    n = (F.length("text") - F.length(F.translate("text", "\n", "")) + 1).cast("long")
    removed = F.when(F.col("gone").isNull(), F.lit(0)).otherwise(F.size(F.filter(lines, lambda x, i: out(i)))).cast("long")
    said = F.coalesce(F.array_join(F.transform("gone", lambda r: F.concat_ws("-", r["a"].cast("string"), r["b"].cast("string"))), ","), F.lit(""))
    return joined.select(F.when(F.col("doc_id") != NO_ID, F.col("doc_id")).alias("doc_id"), n.alias("n_lines"), removed.alias("n_removed"), said.alias("removed"), kept.alias("text"))


def op6_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """drop_repeated_runs() of all ``documents``."""
    return drop_repeated_runs(table(spark, sf_dir, "documents"))
