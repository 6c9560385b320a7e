"""Byte-level BPE as a monoid over texts: encode the leaves, join neighbours, up a tree."""

from __future__ import annotations

import base64
import functools
import heapq
import itertools
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import id_text, table

#: Characters of text, and ids, in one leaf of the tree.
LEAF = 1024
#: Pieces of up to this many characters are remembered with their ids, so many of them.
SHORT, REMEMBERED = 24, 400_000
#: Pieces of up to this many bytes merge without a heap.
FEW = 64


class Codec:
    """Encodes and decodes by a rank file; ``pattern`` splits texts into pieces that merge separately.

    An element of the monoid is (text, starts, counts, ids): the span, the places where its pieces start, the ids
    that each piece has, and all ids. Where a piece starts, all that follows depends on the text from there on only.
    So two neighbours join by splitting a window anew that begins at a piece of the left one which cannot see the
    border, and grows to the right until a piece starts where one of the right element's pieces starts: from
    there on both agree for ever, and before the window nothing has changed.
    """

    #: A piece that ends this many characters before the border was settled without looking past it: runs end at
    #: the character after them, and the longest alternative of fixed length has three characters.
    SIGHT = 3

    def __init__(self, path: str, pattern: str):
        with open(path, "rb") as lines:
            self.ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, lines)}
        self.split = regex.compile(pattern)
        self.bytes_of = [b""] * (max(self.ranks.values()) + 1)
        for token, rank in self.ranks.items():
            self.bytes_of[rank] = token
        self.known: dict[str, tuple[int, ...]] = {}

    def merge(self, data: bytes) -> tuple[int, ...]:
        """The ids of one piece: its bytes, of which the neighbours with the least rank merge first, the leftmost of
        equal ones; a heap of candidates over a linked list."""
        ranks = self.ranks
        if data in ranks:
            return (ranks[data],)
        if len(data) <= FEW:
            return self._merge_few(data)
        parts: list[bytes | None] = [data[k : k + 1] for k in range(len(data))]
        n = len(parts)
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        heap = [(r, k, parts[k] + parts[k + 1]) for k in range(n - 1) if (r := ranks.get(parts[k] + parts[k + 1])) is not None]
        heapq.heapify(heap)
        while heap:
            _, k, both = heapq.heappop(heap)
            j = after[k] if parts[k] is not None else n
            if j >= n or parts[k] + parts[j] != both:
                continue  # one of the two has merged otherwise meanwhile
            parts[k], parts[j] = both, None
            after[k] = j = after[j]
            if j < n:
                before[j] = k
            for x, y in ((before[k], k), (k, j)):
                if x >= 0 and y < n and (r := ranks.get(parts[x] + parts[y])) is not None:
                    heapq.heappush(heap, (r, x, parts[x] + parts[y]))
        return tuple(ranks[x] for x in parts if x is not None)

    def _merge_few(self, data: bytes) -> tuple[int, ...]:
        """The same for few bytes, by a list of the neighbours' ranks."""
        rank, none = self.ranks.get, len(self.bytes_of)
        parts = [data[k : k + 1] for k in range(len(data))]
        pairs = [rank(x + y, none) for x, y in zip(parts, parts[1:])]
        while pairs and (least := min(pairs)) < none:
            k = pairs.index(least)
            parts[k] += parts.pop(k + 1)
            pairs.pop(k)
            if k:
                pairs[k - 1] = rank(parts[k - 1] + parts[k], none)
            if k < len(pairs):
                pairs[k] = rank(parts[k] + parts[k + 1], none)
        return tuple(self.ranks[x] for x in parts)

    def piece(self, text: str) -> tuple[int, ...]:
        ids = self.known.get(text)
        if ids is None:
            ids = self.merge(text.encode())
            if len(text) <= SHORT and len(self.known) < REMEMBERED:
                self.known[text] = ids
        return ids

    def _element(self, text: str) -> tuple:
        pieces = self.split.findall(text)
        ids = list(map(self.piece, pieces))
        ends = list(itertools.accumulate(map(len, pieces)))
        starts = [0, *ends[:-1]] if ends and ends[-1] == len(text) else [m.start() for m in self.split.finditer(text)]
        counts = np.fromiter(map(len, ids), np.int32, len(ids))
        return text, np.array(starts, np.int64), counts, np.fromiter(itertools.chain.from_iterable(ids), np.uint32, int(counts.sum()))

    def join(self, left: tuple, right: tuple) -> tuple:
        (a, a_starts, a_counts, a_ids), (b, b_starts, b_counts, b_ids) = left, right
        if not a or not b:
            return left if a else right
        keep = len(a_starts)
        while keep and (a_starts[keep] if keep < len(a_starts) else len(a)) > len(a) - self.SIGHT:
            keep -= 1  # the piece before keep ends where keep starts
        at = int(a_starts[keep])
        head, width = a[at:], 64
        while True:
            window, whole = head + b[:width], width >= len(b)
            known = set(b_starts[: np.searchsorted(b_starts, width)].tolist())
            fresh, meet = [], None
            for m in self.split.finditer(window):
                if not whole and m.end() > len(window) - self.SIGHT:
                    break  # it may look past the window
                if m.start() - len(head) in known:
                    meet = m.start() - len(head)
                    break
                fresh.append((m.start(), self.piece(m.group())))
            if meet is not None or whole:
                break
            width *= 4
        rest = len(b_starts) if meet is None else int(np.searchsorted(b_starts, meet))
        middle = np.fromiter(itertools.chain.from_iterable(x for _, x in fresh), np.uint32)
        return (
            a + b,
            np.concatenate([a_starts[:keep], np.array([at + k for k, _ in fresh], np.int64), len(a) + b_starts[rest:]]),
            np.concatenate([a_counts[:keep], np.array([len(x) for _, x in fresh], np.int32), b_counts[rest:]]),
            np.concatenate([a_ids[: len(a_ids) - int(a_counts[keep:].sum())], middle, b_ids[int(b_counts[:rest].sum()) :]]),
        )

    def _tree(self, text: str, leaf: int) -> tuple:
        if len(text) <= leaf:
            return self._element(text)
        half = len(text) // 2
        return self.join(self._tree(text[:half], leaf), self._tree(text[half:], leaf))

    def encode(self, text: str, leaf: int = LEAF) -> np.ndarray:
        """The ids as unsigned 32-bit integers, joined up the tree from leaves of up to ``leaf`` characters."""
        return self._tree(text, leaf)[3]

    def decode(self, ids: np.ndarray, leaf: int = LEAF) -> bytes:
        """Concatenates up the tree."""
        if len(ids) <= leaf:
            of = self.bytes_of
            return b"".join([of[i] for i in ids.tolist()])
        half = len(ids) // 2
        return self.decode(ids[:half], leaf) + self.decode(ids[half:], leaf)


@functools.lru_cache(4)
def codec(path: str, pattern: str) -> Codec:
    return Codec(path, pattern)


def encode(docs: DataFrame, path: str, pattern: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, ids: binary, the ids as little-endian unsigned 32-bit integers. Null and empty texts have no ids.

    ``path`` must be readable on every executor. One pass without a shuffle; rows keep their order.
    """

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = codec(path, pattern)
        for batch in batches:
            ids = [own.encode(x.as_py()).astype("<u4").tobytes() for x in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(ids, pa.binary())], names=["doc_id", "ids"])

    return id_text(docs, id_col, text_col).mapInArrow(work, "doc_id long, ids binary")


def decode(encoded: DataFrame, path: str, pattern: str) -> DataFrame:
    """doc_id, ids, decoded: binary, the bytes of the ids."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = codec(path, pattern)
        for batch in batches:
            texts = [own.decode(np.frombuffer(x.as_buffer(), "<u4")) for x in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(texts, pa.binary())], names=["doc_id", "ids", "decoded"])

    return encoded.select("doc_id", F.coalesce("ids", F.lit(b"")).alias("ids")).mapInArrow(work, "doc_id long, ids binary, decoded binary")


def round_trip(docs: DataFrame, path: str, pattern: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """decode(encode(docs)) in one pass: a task has one worker, and one codec, instead of two."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = codec(path, pattern)
        for batch in batches:
            ids = [own.encode(x.as_py()) for x in batch.column(1)]
            packed, texts = [x.astype("<u4").tobytes() for x in ids], [own.decode(x) for x in ids]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(packed, pa.binary()), pa.array(texts, pa.binary())], names=["doc_id", "ids", "decoded"])

    return id_text(docs, id_col, text_col).mapInArrow(work, "doc_id long, ids binary, decoded binary")


def digests(docs: DataFrame) -> DataFrame:
    """doc_id, n_tokens and the digests of ids and decoded bytes, under the production vocabulary."""
    import public_tokenizers

    out = round_trip(docs, public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN)
    return out.select("doc_id", (F.octet_length("ids") / 4).cast("long").alias("n_tokens"), F.sha2("ids", 256).alias("ids_sha256"), F.sha2("decoded", 256).alias("decoded_sha256"))


def op3_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    """digests() of all ``documents``."""
    return digests(table(spark, sf_dir, "documents"))
