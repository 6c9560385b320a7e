"""Benchmark passages in training texts, found by spaced seeds and verified with substitutions."""

from __future__ import annotations

import math
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Workspace, drop_rows, id_text, table, text_hash

#: A passage: this many tokens in a row (the whole item if it is shorter), of which SHARE agree place by place.
WINDOW, SHARE = 13, 0.8
#: Token positions that each seed compares; the others may be substituted. Wherever two tokens of a window are
#: substituted, as many as SHARE allows, some seed fits between them, so that no such passage is missed.
SEEDS = ((0, 1, 2, 5, 7, 8), (0, 2, 3, 5, 6, 10), (0, 5, 6, 7, 9, 10))
#: Tokens of benchmark items that one broadcast holds; larger benchmarks go in blocks.
BLOCK_TOKENS = 2_000_000
_WORD = re.compile(r"\w+")
_MULTIPLIERS = np.random.default_rng(11).integers(1, 1 << 63, 64, dtype=np.uint64) | np.uint64(1)
_FILTER_BITS = 22


def short_seeds(n: int) -> list[tuple[int, ...]]:
    """Seeds for items of ``n`` tokens, fewer than WINDOW: each of one more classes of places than may be substituted, so
    that some class holds no substitution."""
    classes = n - math.ceil(round(SHARE * n, 9)) + 1
    return [tuple(range(r, n, classes)) for r in range(classes)]


def tokens(text: str) -> list[str]:
    return _WORD.findall(text.lower())


def seed_hashes(ids: np.ndarray, seed: tuple[int, ...]) -> np.ndarray:
    """One hash for each place where the seed fits."""
    n = len(ids) - seed[-1]
    if n <= 0:
        return np.zeros(0, np.uint64)
    wide = ids.astype(np.uint64)
    out = np.zeros(n, np.uint64)
    for k, at in enumerate(seed):
        out += wide[at : at + n] * _MULTIPLIERS[k]
    return out ^ (out >> np.uint64(29))


class Index:
    """Seeds of a block of benchmark items."""

    def __init__(self, items: list[tuple[int, str]]):
        words = [(i, tokens(t)) for i, t in items]
        words = [(i, w) for i, w in words if w]
        self.item_ids = np.array([i for i, _ in words], np.int64)
        vocabulary: dict[str, int] = {}
        for _, w in words:
            for x in w:
                vocabulary.setdefault(x, len(vocabulary) + 1)
        self.vocabulary = vocabulary
        self.items = [np.array([vocabulary[x] for x in w], np.int32) for _, w in words]
        short = sorted({len(x) for x in self.items if len(x) < WINDOW})
        self.seeds = [*((s, None) for s in SEEDS), *((s, n) for n in short for s in short_seeds(n))]
        self.tables = []
        for seed, n in self.seeds:
            own = [k for k, x in enumerate(self.items) if (len(x) >= WINDOW if n is None else len(x) == n)]
            hashes = [seed_hashes(self.items[k], seed) for k in own]
            h = np.concatenate(hashes) if hashes else np.zeros(0, np.uint64)
            item = np.repeat(np.array(own, np.int32), [len(x) for x in hashes]) if own else np.zeros(0, np.int32)
            place = np.concatenate([np.arange(len(x), dtype=np.int32) for x in hashes]) if hashes else np.zeros(0, np.int32)
            order = np.argsort(h, kind="stable")
            maybe = np.zeros(1 << _FILTER_BITS, bool)
            maybe[(h >> np.uint64(64 - _FILTER_BITS)).astype(np.int64)] = True
            self.tables.append((h[order], item[order], place[order], maybe))

    def matches(self, text: str) -> list[tuple[int, int, int, int]]:
        """(item's id, first token of the passage in the text, tokens, agreeing tokens), the best of each item."""
        get = self.vocabulary.get
        found = [get(x, 0) for x in tokens(text)]
        ids = np.array(found, np.int32)
        aligned: set[tuple[int, int]] = set()
        for (seed, _), (h, item, place, maybe) in zip(self.seeds, self.tables):
            got = seed_hashes(ids, seed)
            at = np.flatnonzero(maybe[(got >> np.uint64(64 - _FILTER_BITS)).astype(np.int64)]) if len(got) and len(h) else ()
            if len(at):
                low, high = np.searchsorted(h, got[at], "left"), np.searchsorted(h, got[at], "right")
                for p, a, b in zip(at[high > low].tolist(), low[high > low].tolist(), high[high > low].tolist()):
                    aligned.update(zip(item[a:b].tolist(), (p - place[a:b]).tolist()))
        best: dict[int, tuple[int, int, int, int]] = {}
        for k, shift in aligned:
            whole = self.items[k]
            a, b = max(0, -shift), min(len(whole), len(ids) - shift)
            need = min(WINDOW, len(whole))
            if b - a < need:
                continue
            same = np.concatenate([[0], np.cumsum(whole[a:b] == ids[a + shift : b + shift])])
            runs = same[need:] - same[:-need]
            if runs.max() >= SHARE * need:
                good = np.flatnonzero(runs >= SHARE * need)
                first, last = int(good[0]), int(good[-1]) + need
                row = (int(self.item_ids[k]), a + shift + first, last - first, int(same[last] - same[first]))
                if k not in best or row[3] > best[k][3] or row[3] == best[k][3] and row[1] < best[k][1]:
                    best[k] = row
        return sorted(best.values())


def contaminated(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text", block_tokens: int = BLOCK_TOKENS) -> DataFrame:
    """A row for each document and benchmark item that share a passage: doc_id, item_id, first_token, n_tokens, n_same.

    A passage is WINDOW tokens in a row (a whole item if it is shorter) of which at least SHARE agree with the
    item's, place by place, so that substitutions do not hide it: none is missed, whatever the item's length. Null or
    empty texts and items never match; repeated rows give repeated results, null ids are kept. Benchmarks of over ``block_tokens`` octets / 2 are taken in blocks of
    items, each small enough to be sent to every task; documents never move.
    """
    return _hits(id_text(docs, id_col, text_col), benchmark, block_tokens)


def _hits(texts: DataFrame, benchmark: DataFrame, block_tokens: int = BLOCK_TOKENS) -> DataFrame:
    """contaminated() of ``texts``: doc_id, text, and any columns that the rows carry along."""
    spark = texts.sparkSession
    carried = [c for c in texts.columns if c not in ("doc_id", "text")]
    texts = texts.select("doc_id", "text", *carried)
    kinds = "doc_id long, item_id long, first_token long, n_tokens long, n_same long" + "".join(f", {c} {dict(texts.dtypes)[c]}" for c in carried)
    items = benchmark.select(F.col("item_id").cast("long").alias("item_id"), F.col("text").alias("text")).where("text is not null")
    octets = items.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    blocks = max(1, -(-octets // (2 * block_tokens)))
    out = None
    for k in range(blocks):
        part = items if blocks == 1 else items.where(F.pmod(F.xxhash64("item_id"), F.lit(blocks)) == k)
        shared = spark.sparkContext.broadcast(Index([tuple(r) for r in part.collect()]))  # a block of bounded size

        def work(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                rows = [(k, *m) for k, x in enumerate(batch.column(1)) for m in shared.value.matches(x.as_py())]
                owner, *columns = [pa.array(c, pa.int64()) for c in (zip(*rows) if rows else [()] * 5)]
                yield pa.RecordBatch.from_arrays([batch.column(0).take(owner), *columns, *(c.take(owner) for c in batch.columns[2:])], names=["doc_id", "item_id", "first_token", "n_tokens", "n_same", *carried])

        hits = texts.mapInArrow(work, kinds)
        out = hits if out is None else out.unionByName(hits)
    return out


def clean(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of ``docs`` that share no passage with the benchmark, with all their columns; ids may be null or repeat."""
    hits = _hits(id_text(docs, id_col, text_col).withColumn("th", text_hash()), benchmark)
    return drop_rows(docs, hits, Workspace(docs.sparkSession, "clean"), id_col, text_col)


def op8_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    """contaminated() of all ``documents`` and benchmark items; documents without a passage have no row."""
    return contaminated(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
