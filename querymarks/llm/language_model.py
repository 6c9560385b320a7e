"""Deleted interpolation: bigram, unigram and uniform estimates, mixed by buckets of the context's frequency.

Counting goes by blocks of text. A block knows its distinct words and word pairs; it sends them, sorted and packed,
to groups dealt out by hash, and gets back the corpus counts in the same order. So each block sends a key once,
however frequent it is, nothing is hot, and a text's tokens never travel as rows.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Workspace, id_text, table, word_blocks

#: Rows whose crc32(id as text) mod 7 is HELD_OUT are never learnt from; of the others, one in DEVELOP fits the weights.
MODULUS, HELD_OUT, DEVELOP = 7, 2, 20
#: Octets of text in a block and in a group at least, and octets of a block that meet in one group at least.
BLOCK, MEETING = 8 << 20, 500
ROUNDS, START, LEAST_WEIGHT = 15, (0.5, 0.4, 0.1), 1e-6
#: Buckets: one more than the bits of the context's count, up to this many.
BUCKETS = 24
END = b""


def _pack(x: np.ndarray) -> bytes:
    """Compressed by planes of bytes, so that the high ones, mostly zero, take no room."""
    return zstandard.compress(np.ascontiguousarray(x.view(np.uint8).reshape(-1, x.itemsize).T).tobytes(), 1)


def _unpack(data: bytes, kind: type) -> np.ndarray:
    raw = np.frombuffer(zstandard.decompress(data), np.uint8) if len(data) else np.zeros(0, np.uint8)
    size = np.dtype(kind).itemsize
    return np.ascontiguousarray(raw.reshape(size, -1).T).reshape(-1).view(kind)


class _Vocabulary(dict):
    def __missing__(self, word: bytes) -> int:
        self[word] = n = len(self)
        return n


class _Block:
    """Texts, or parts of very long ones, as numbers of the block's own words; 0 is the end."""

    def __init__(self, name: str, dev: bool):
        self.name, self.dev = name, dev
        self.words = _Vocabulary({END: 0})
        self.ids, self.meta, self.size = [], [], 0

    def add(self, doc_id: int | None, held: bool, owner: str, tokens: list[bytes], lead: bytes, last: bool, size: int) -> None:
        n = len(tokens) + last
        ids = np.fromiter(map(self.words.__getitem__, tokens), np.int32, len(tokens))
        self.ids.append(np.append(ids, np.int32(0)) if last else ids)
        self.meta.append((doc_id, held, owner, n, self.words[lead]))
        self.size += size

    def rows(self) -> pa.RecordBatch:
        doc_ids, held, owners, lens, leads = zip(*self.meta)
        values = {
            "block": pa.array([self.name]), "dev": pa.array([self.dev]), "doc_ids": pa.array([list(doc_ids)], pa.list_(pa.int64())), "held": pa.array([np.array(held, np.uint8).tobytes()], pa.binary()),
            "owners": pa.array([list(owners)], pa.list_(pa.string())), "lens": pa.array([np.array(lens, np.int32).tobytes()], pa.binary()), "leads": pa.array([np.array(leads, np.int32).tobytes()], pa.binary()),
            "words": pa.array([zstandard.compress(b" ".join(self.words), 1)], pa.binary()), "ids": pa.array([_pack(np.concatenate(self.ids))], pa.binary()),
        }
        return pa.RecordBatch.from_arrays(list(values.values()), names=list(values))


BLOCKS = "block string, dev boolean, doc_ids array<long>, held binary, owners array<string>, lens binary, leads binary, words binary, ids binary"


def make_blocks(docs: DataFrame, block: int, id_col: str, text_col: str) -> DataFrame:
    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        task, made = TaskContext.get().partitionId(), 0
        open_: dict[bool, _Block] = {}
        for batch in batches:
            for row, (doc_id, text) in enumerate(zip(batch.column(0).to_pylist(), batch.column(1))):
                crc = zlib.crc32(b"" if doc_id is None else str(doc_id).encode())
                held = crc % MODULUS == HELD_OUT
                dev = not held and crc // MODULUS % DEVELOP == 0
                data = text.as_buffer().to_pybytes().lower()
                parts = word_blocks(data, block) if len(data) > block else iter([data.split()])
                owner = f"{task}-{made}-{row}" if len(data) > block else ""
                lead, now = END, next(parts, [])
                while now is not None:
                    then = next(parts, None)
                    if dev not in open_:
                        open_[dev], made = _Block(f"{task}-{made}", dev), made + 1
                    open_[dev].add(doc_id, held, owner, now, lead, then is None, min(len(data), block))
                    if open_[dev].size >= block:
                        yield open_.pop(dev).rows()
                    lead, now = (now[-1] if now else lead), then
        for x in open_.values():
            yield x.rows()

    return id_text(docs, id_col, text_col).mapInArrow(work, BLOCKS)


class _Tokens:
    """What a block's row says: its words, and for each token its word and the one before."""

    def __init__(self, row: dict):
        self.words = zstandard.decompress(row["words"]).split(b" ")
        self.ids = _unpack(row["ids"], np.int32)
        self.lens = np.frombuffer(row["lens"], np.int32)
        self.held = np.frombuffer(row["held"], np.uint8).astype(bool)
        starts = np.cumsum(self.lens) - self.lens
        self.before = np.concatenate([[0], self.ids[:-1]]).astype(np.int32) if len(self.ids) else self.ids
        some = self.lens > 0
        self.before[starts[some]] = np.frombuffer(row["leads"], np.int32)[some]
        self.starts = starts
        self.train = np.repeat(~self.held, self.lens)
        hashes = np.fromiter((xxhash.xxh64_intdigest(w, 1) for w in self.words), np.uint64, len(self.words))
        self.word_order = np.argsort(hashes, kind="stable")
        self.word_hashes = hashes[self.word_order]
        pairs, self.pair_of = np.unique(self.before.astype(np.int64) * len(self.words) + self.ids, return_inverse=True)
        key = hashes[pairs // len(self.words)] * np.uint64(0x9E3779B97F4A7C15) + hashes[pairs % len(self.words)]
        key ^= key >> np.uint64(32)
        key *= np.uint64(0xD6E8FEB86659FD93)
        key ^= key >> np.uint64(29)
        self.pair_order = np.argsort(key, kind="stable")
        self.keys = key[self.pair_order]


def _cut(sorted_keys: np.ndarray, bits: int) -> np.ndarray:
    """Where each group's keys begin in sorted ones, and their end."""
    return np.searchsorted(sorted_keys >> np.uint64(64 - bits) if bits else sorted_keys * np.uint64(0), np.arange((1 << bits) + 1, dtype=np.uint64))


def packs(blocks: DataFrame, bits: int) -> DataFrame:
    """Each block's distinct words and pairs with their training counts, a row for each group (2^bits of each)."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                t = _Tokens(row)
                words = np.bincount(t.ids[t.train], minlength=len(t.words))[t.word_order]
                pairs = np.bincount(t.pair_of[t.train], minlength=len(t.keys))[t.pair_order]
                out = []
                at = _cut(t.word_hashes, bits)
                for g in np.flatnonzero(np.diff(at)).tolist():
                    of = slice(at[g], at[g + 1])
                    out.append((g, "word", row["block"], row["dev"], zstandard.compress(b" ".join(t.words[k] for k in t.word_order[of]), 1), _pack(words[of].astype(np.uint32))))
                at = _cut(t.keys, bits)
                for g in np.flatnonzero(np.diff(at)).tolist():
                    of = slice(at[g], at[g + 1])
                    out.append((g, "pair", row["block"], row["dev"], _pack(np.diff(t.keys[of], prepend=np.uint64(0))), _pack(pairs[of].astype(np.uint32))))
                names = ["group", "kind", "block", "dev", "keys", "n"]
                yield pa.RecordBatch.from_arrays([pa.array(x, k) for x, k in zip(zip(*out), (pa.int32(), pa.string(), pa.string(), pa.bool_(), pa.binary(), pa.binary()))], names=names)

    return blocks.mapInArrow(work, "group int, kind string, block string, dev boolean, keys binary, n binary")


COUNTED = "block string, dev boolean, kind string, group int, c binary, d binary, tokens long, types long, dev_tokens long"


def _merge(frame: pd.DataFrame) -> pd.DataFrame:
    """One group: the counts of all blocks added up, and given back to each in its own order."""
    kind = frame["kind"].iat[0]
    if kind == "word":
        lists = [zstandard.decompress(x).split(b" ") for x in frame["keys"]]
        sizes = [len(x) for x in lists]
        flat = np.empty(sum(sizes), object)
        flat[:] = [w for x in lists for w in x]
        inverse, unique = pd.factorize(flat)
    else:
        keys = [np.cumsum(_unpack(x, np.uint64), dtype=np.uint64) for x in frame["keys"]]
        sizes = [len(x) for x in keys]
        unique, inverse = np.unique(np.concatenate(keys), return_inverse=True)
    n = np.concatenate([_unpack(x, np.uint32) for x in frame["n"]]).astype(float)
    dev = np.repeat(frame["dev"].to_numpy(bool), sizes)
    c = np.bincount(inverse, n, len(unique)).astype(np.int64)
    d = np.bincount(inverse[dev], n[dev], len(unique)).astype(np.int64)
    out, at = [], 0
    for block, is_dev, group, size in zip(frame["block"], frame["dev"], frame["group"], sizes):
        own = inverse[at : at + size]
        said = (int(c.sum()), int((c > 0).sum()), int(d.sum())) if kind == "word" and not at else (0, 0, 0)
        out.append((block, bool(is_dev), kind, int(group), _pack(c[own]), _pack(d[own]) if is_dev else b"", *said))
        at += size
    return pd.DataFrame(out, columns=["block", "dev", "kind", "group", "c", "d", "tokens", "types", "dev_tokens"])


def _counts_of(t: _Tokens, counted: pd.DataFrame, column: str) -> tuple[np.ndarray, np.ndarray]:
    """Corpus counts of the block's words and pairs, in the block's own numbering."""
    out = []
    for kind, order in (("word", t.word_order), ("pair", t.pair_order)):
        rows = counted[counted["kind"] == kind].sort_values("group")
        values = np.zeros(len(order), np.int64)
        values[order] = np.concatenate([_unpack(x, np.int64) for x in rows[column]])
        out.append(values)
    return out[0], out[1]


def _bucket(context: np.ndarray) -> np.ndarray:
    return np.minimum(BUCKETS - 1, np.ceil(np.log2(context + 1.0))).astype(np.int64)


def weights(events: DataFrame, types: int, rounds: int = ROUNDS) -> list[tuple[float, float, float]]:
    """Mixture weights (pair, word, uniform) for each bucket, by expectation-maximisation.

    ``events``: bucket, f2, f1, n: the estimates that left the development texts out, and how often a token of
    those texts had them. A round adds up the expected origins of all events; only BUCKETS rows come back.
    """
    mix = [START] * BUCKETS
    for _ in range(rounds):
        part = lambda k: F.element_at(F.array(*(F.lit(float(m[k])) for m in mix)), F.col("bucket").cast("int") + 1)  # noqa: B023, E731  used at once
        shares = (part(0) * F.col("f2"), part(1) * F.col("f1"), part(2) / F.lit(types + 1.0))
        total = shares[0] + shares[1] + shares[2]
        got = events.groupBy("bucket").agg(*(F.sum(F.col("n") * s / total).alias(f"s{k}") for k, s in enumerate(shares))).collect()
        for r in got:
            three = np.maximum(np.array([r["s0"], r["s1"], r["s2"]]), 0)
            if three.sum() > 0:
                three = np.maximum(three / three.sum(), LEAST_WEIGHT)
                mix[r["bucket"]] = tuple((three / three.sum()).tolist())
    return mix


def score_texts(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", block: int = BLOCK) -> DataFrame:
    """Per row of ``docs``: doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score.

    Tokens are the words of the text, A-Z lower-cased, and one end. ``score``: log10 of the probability of all
    tokens, each given the one before (the end, at the start). Pairs are known by 64-bit hashes; words as they
    are. Null texts are empty and have the end alone; a null id counts as the empty text in the choice of rows;
    without any training row all estimates are uniform. A text longer than a block is cut between words and its
    parts' sums are added.
    """
    spark = docs.sparkSession
    ws = Workspace(spark, "lm")
    octets = docs.agg(F.sum(F.octet_length(text_col))).first()[0] or 0
    block = int(max(block, (MEETING * octets) ** 0.5))
    bits = max(0, int(octets / block).bit_length())
    blocks = ws.save(make_blocks(docs, block, id_col, text_col), "blocks")
    counted = ws.save(packs(blocks, bits).groupBy("kind", "group").applyInPandas(_merge, COUNTED), "counted")
    told = counted.agg(*(F.coalesce(F.sum(c), F.lit(0)) for c in ("tokens", "types", "dev_tokens"))).first()
    n, types, dev_n = (int(x) for x in told)

    def left_out(own: pd.DataFrame, got: pd.DataFrame) -> pd.DataFrame:
        if own.empty:
            return pd.DataFrame({"bucket": [], "f2": [], "f1": [], "n": []})
        t = _Tokens(own.iloc[0])
        (c1, c2), (d1, d2) = _counts_of(t, got, "c"), _counts_of(t, got, "d")
        w, p = c1 - d1, c2 - d2
        seen, first, times = np.unique(t.pair_of, return_index=True, return_counts=True)
        context, word = w[t.before[first]], w[t.ids[first]]
        out = pd.DataFrame({"bucket": _bucket(context), "f2": p[seen] / np.maximum(context, 1), "f1": word / max(1, n - dev_n), "n": times})
        return out.groupby(["bucket", "f2", "f1"], as_index=False).sum()

    pair = lambda df, c: df.groupBy("block").cogroup(c.groupBy("block"))
    events = ws.save(pair(blocks.where("dev"), counted.where("dev")).applyInPandas(left_out, "bucket long, f2 double, f1 double, n long"), "events")
    mix = np.array(weights(events, types))

    def score(own: pd.DataFrame, got: pd.DataFrame) -> pd.DataFrame:
        row = own.iloc[0]
        t = _Tokens(row)
        c1, c2 = _counts_of(t, got, "c")
        context, word = c1[t.before], c1[t.ids]
        m = mix[_bucket(context)]
        p = m[:, 0] * c2[t.pair_of] / np.maximum(context, 1) + m[:, 1] * word / max(1, n) + m[:, 2] / (types + 1) if n else np.ones(len(word))
        add = lambda x: np.add.reduceat(np.append(x, 0), np.minimum(t.starts, len(x))) * (t.lens > 0) if len(t.lens) else x
        return pd.DataFrame({"doc_id": pd.array([None if x is None or x != x else int(x) for x in row["doc_ids"]], "Int64"), "owner": row["owners"], "held_out": t.held, "n_tokens": t.lens.astype(np.int64), "n_known": add((word > 0).astype(np.int64)), "base_score": add(np.log10((word + 1) / (n + types + 1))), "score": add(np.log10(p))})

    parts = pair(blocks, counted).applyInPandas(score, "doc_id long, owner string, held_out boolean, n_tokens long, n_known long, base_score double, score double")
    parts = ws.save(parts, "parts")
    sums = [F.sum(c).alias(c) for c in ("n_tokens", "n_known", "base_score", "score")]
    whole = parts.where("owner = ''").drop("owner")
    long_ = parts.where("owner <> ''").groupBy("owner", "doc_id", "held_out").agg(*sums).drop("owner")
    return whole.unionByName(long_).select("doc_id", "held_out", "n_tokens", "n_known", F.lit(n).cast("long").alias("train_tokens"), "base_score", "score")


def op2_language_model(spark: SparkSession, sf_dir: str) -> DataFrame:
    """score_texts() of all ``documents``."""
    return score_texts(table(spark, sf_dir, "documents"))
