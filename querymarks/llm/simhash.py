"""SimHash fingerprints and covering locality-sensitive hashing over them."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Workspace, drop_rows, id_text, table, text_hash, word_blocks
from .components import connected

SEED = 42
#: Buckets of up to this many fingerprints compare pairs; larger ones meet in the points at one bit's distance.
PAIRWISE = 32
#: Classes of shingles: about so many shingles in one, so many classes used; hashes in a sketch.
CLASS_SIZE, CLASSES, SKETCH = 4, 16, 512
#: Documents of a bucket that one task holds from each side; larger buckets meet so many of their members first.
BLOCK, HEADS = 512, 16
#: Hashes of whole texts that one task holds from each side, but for a text that has more.
VOLUME = 1 << 22
#: Similarities that a sketch puts this near to the threshold (five standard errors) are computed from all hashes.
MARGIN = 0.09


def fingerprint(data: bytes, words: int = 3) -> int:
    """Bit b is set if it is set in over half of the hashes of all shingles, repeats included; no words: zero."""
    sums, n, tail = np.zeros(64, np.int64), 0, []
    hashed = xxhash.xxh64_intdigest
    for block in word_blocks(data.lower()):
        tokens = tail + block
        if len(tokens) >= words:
            got = np.fromiter((hashed(b" ".join(x), SEED) for x in zip(*(tokens[k:] for k in range(words)))), np.uint64)
            bits = np.unpackbits(got.view(np.uint8), bitorder="little").reshape(-1, 64)
            sums += bits.sum(0, dtype=np.int32)
            n += len(got)
        tail = tokens[-(words - 1) :] if words > 1 else []
    if not n and tail:
        sums += np.unpackbits(np.array([hashed(b" ".join(tail), SEED)], np.uint64).view(np.uint8), bitorder="little")
        n = 1
    return int(np.packbits(2 * sums > n, bitorder="little").view(np.uint64)[0]) if n else 0


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = 3) -> DataFrame:
    """doc_id, fp (the 64 bits as a signed long), one row per row of ``docs``."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            got = np.fromiter((fingerprint(x.as_buffer().to_pybytes(), words) for x in batch.column(1)), np.uint64, batch.num_rows)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(got.view(np.int64))], names=["doc_id", "fp"])

    return id_text(docs, id_col, text_col).mapInArrow(work, "doc_id long, fp long")


def covering_masks(radius: int) -> list[int]:
    """2^(radius+1)-1 masks of 64 bits, as signed longs.

    Each bit position gets a nonzero vector of radius+1 bits, and each nonzero v gives the mask of the positions
    whose vector has an odd product with v. The vectors of any ``radius`` positions leave some v orthogonal to all
    of them, so that its mask hides every differing position: that pair agrees on the masked bits.
    """
    full = (1 << (radius + 1)) - 1
    masks = [sum(1 << i for i in range(64) if ((1 + i % full) & v).bit_count() & 1) for v in range(1, full + 1)]
    return [m - (1 << 64) if m >> 63 else m for m in masks]


def _signed(bit: int) -> int:
    return (1 << bit) - (1 << 64) if bit == 63 else 1 << bit


def fingerprint_links(fps: DataFrame, ws: Workspace, radius: int = 2) -> DataFrame:
    """Links (a, b) whose connected components are those of all pairs of distinct ``fp`` at ``radius`` bits or fewer.

    Buckets of up to PAIRWISE fingerprints compare their pairs. A larger bucket would grow with the square of its
    size; there each fingerprint goes to all points within radius/2 bits, and links to the least fingerprint that
    shares a point: two fingerprints share one if and only if they differ in ``radius`` bits or fewer (even radius).
    """
    if radius % 2:
        raise ValueError("the radius must be even")
    masks = covering_masks(radius)
    dealt = fps.select("fp", F.explode(F.array(*(F.struct(F.lit(k).alias("t"), F.col("fp").bitwiseAND(F.lit(m)).alias("key")) for k, m in enumerate(masks)))).alias("x")).select("fp", "x.t", "x.key")
    dealt = ws.save(dealt, "dealt")
    sizes = dealt.groupBy("t", "key").agg(F.count(F.lit(1)).alias("n")).where("n > 1")
    met = ws.save(dealt.join(sizes, ["t", "key"]), "met")
    few = met.where(F.col("n") <= PAIRWISE)
    pairs = few.alias("a").join(few.alias("b"), (F.col("a.t") == F.col("b.t")) & (F.col("a.key") == F.col("b.key")) & (F.col("a.fp") < F.col("b.fp")) & (F.bit_count(F.col("a.fp").bitwiseXOR(F.col("b.fp"))) <= radius)).select(F.col("a.fp").alias("a"), F.col("b.fp").alias("b"))
    points = met.where(F.col("n") > PAIRWISE).select("fp").distinct().select("fp", F.col("fp").alias("point"))
    for _ in range(radius // 2):
        flips = F.array(F.col("point"), *(F.col("point").bitwiseXOR(F.lit(_signed(b))) for b in range(64)))
        points = points.select("fp", F.explode(flips).alias("point"))
    if radius > 2:
        points = points.distinct()
    least = points.groupBy("point").agg(F.min("fp").alias("a"), F.count(F.lit(1)).alias("n")).where("n > 1")
    meets = points.join(least, "point").where("fp <> a").select("a", F.col("fp").alias("b"))
    return pairs.unionByName(meets).distinct()


def simhash_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = 3, radius: int = 2) -> DataFrame:
    """Per row of ``docs``: doc_id, fp, component_id (the smallest doc_id reachable over links, itself included).

    Texts without words have fingerprint zero and link like any other. Rows with equal fingerprints are one vertex,
    so copies are never expanded into pairs. Null ids are passed over in the minimum; an empty table gives no rows.
    """
    ws = Workspace(docs.sparkSession, "simhash")
    each = ws.save(fingerprints(docs, id_col, text_col, words), "fingerprints")
    least = ws.save(each.groupBy("fp").agg(F.min("doc_id").alias("least")), "distinct")
    roots = connected(fingerprint_links(least.select("fp"), ws, radius), ws)
    placed = least.join(roots.select(F.col("v").alias("fp"), "root"), "fp", "left").select("fp", "least", F.coalesce("root", "fp").alias("root"))
    placed = ws.save(placed, "placed")
    named = placed.groupBy("root").agg(F.min("least").alias("component_id"))
    return each.join(placed.join(named, "root").select("fp", "component_id"), "fp").select("doc_id", "fp", "component_id")


def shingle_hashes(data: bytes, words: int = 5) -> np.ndarray:
    """The distinct hashes of a text's word shingles (fewer words: of the whole sequence; none: no hash), sorted."""
    out, tail, hashed = [], [], xxhash.xxh64_intdigest
    some = False
    for block in word_blocks(data.lower()):
        tokens = tail + block
        if len(tokens) >= words:
            some = True
            out.append(np.unique(np.fromiter((hashed(b" ".join(x), SEED) for x in zip(*(tokens[k:] for k in range(words)))), np.uint64)))
        tail = tokens[-(words - 1) :]
    if not some and tail:
        return np.array([hashed(b" ".join(tail), SEED)], np.uint64)
    return np.unique(np.concatenate(out)) if out else np.zeros(0, np.uint64)


def majority(hashes: np.ndarray, starts: np.ndarray) -> np.ndarray:
    """The SimHash of each stretch of ``hashes`` that begins at ``starts``."""
    bits = np.unpackbits(hashes.view(np.uint8), bitorder="little").reshape(-1, 64)
    sums = np.add.reduceat(bits, starts, axis=0, dtype=np.int64)
    sizes = np.diff(np.append(starts, len(hashes)))
    return np.packbits(2 * sums > sizes[:, None], axis=1, bitorder="little").view(np.uint64).reshape(-1)


def class_keys(hashes: np.ndarray) -> np.ndarray:
    """Keys of SimHashes over classes of shingles, which similar texts share.

    A class holds the shingles whose hashes end in the same bits, so that it is the same class in any text; there are
    enough classes for about CLASS_SIZE shingles in each, and CLASSES of them are used, at the two levels about
    that size, one of which texts of similar size have in common.
    """
    level = max(0, int(np.floor(np.log2(max(1.0, len(hashes) / CLASS_SIZE)))))
    keys = []
    for bits in (level, level + 1):
        own = hashes & np.uint64((1 << bits) - 1)
        chosen = own < CLASSES
        order = np.argsort(own[chosen], kind="stable")
        members, cls = hashes[chosen][order], own[chosen][order]
        if len(members):
            starts = np.flatnonzero(np.diff(cls, prepend=cls[0] + np.uint64(1)))
            keys.append(majority(members, starts) * np.uint64(0x9E3779B97F4A7C15) ^ (cls[starts] + np.uint64(bits << 8)))
    return np.concatenate(keys) if keys else np.zeros(0, np.uint64)


def estimated_jaccard(a: np.ndarray, b: np.ndarray, size: int = SKETCH) -> float:
    """Jaccard similarity of two bottom sketches: of the least ``size`` hashes of both texts, the share that both have."""
    union = np.union1d(a, b)[:size]
    return float(np.isin(union, np.intersect1d(a, b, assume_unique=True), assume_unique=True).sum()) / max(1, len(union))


def join_trees(tree: np.ndarray, x: int, ys: np.ndarray) -> list[tuple[int, int]]:
    """A link from ``x`` to each other tree among ``ys``, which become one with its own."""
    trees, first = np.unique(tree[ys], return_index=True)
    other = trees != tree[x]
    tree[np.isin(tree, trees[other])] = tree[x]
    return [(x, y) for y in ys[first[other]]]


def compare(key: tuple[pa.Scalar, ...], rows: pa.Table, similarity: float) -> pa.Table:
    """a, b: links between the rows with ``side`` and those without it, by sketches; a > b. And a, key, side, n without b:
    rows with an unsure partner in another tree.

    Of two sketches the hashes up to the least of their ends are known whole; their Jaccard similarity is exact where
    no sketch is cut off, else an estimate, and unsure within MARGIN of the threshold. Rows of one ``part`` are linked
    already. Of the links only a forest comes back and of the unsure pairs only their ends: no more than two rows a row.
    """
    side, ids = np.array(rows["side"], bool), np.array(rows["doc_id"], np.int64)
    sizes = np.array(rows["n"], np.int64)
    tree = np.unique(np.array(rows["part"], np.int64), return_inverse=True)[1]
    low = [np.frombuffer(x.as_buffer(), "<u4") for x in rows["low"]]
    cut = np.array([len(x) for x in low]) < sizes
    top = np.array([x[-1] if c else 0xFFFFFFFF for x, c in zip(low, cut)], np.uint32)
    xs, ys = np.flatnonzero(side), np.flatnonzero(~side)
    found, doubtful = [], []
    if len(xs) and len(ys):
        flat = np.concatenate([low[y] for y in ys])
        starts = np.cumsum([0] + [len(low[y]) for y in ys[:-1]])
        known, place = np.unique(flat, return_inverse=True)
        for x in xs:
            own = np.isin(known, low[x], assume_unique=True)
            shared = np.add.reduceat(own[place], starts, dtype=np.int64)
            mine = np.searchsorted(low[x], top[ys], "right")
            theirs = np.add.reduceat(flat <= top[x], starts, dtype=np.int64)
            union = mine + theirs - shared
            fits = np.minimum(sizes[x], sizes[ys]) >= similarity * np.maximum(sizes[x], sizes[ys]) - 1e-9
            vague = cut[x] | cut[ys]
            high = fits & (shared >= (similarity + np.where(vague, MARGIN, 0.0)) * union - 1e-9)
            unsure = fits & vague & ~high & (shared > (similarity - MARGIN) * union)
            doubtful.append((x, ys[unsure & (tree[ys] != tree[x])]))
            found.extend(join_trees(tree, x, ys[high]))
    ends = np.zeros(len(ids), bool)
    for x, others in doubtful:
        others = others[tree[others] != tree[x]]
        ends[others] = True
        ends[x] |= len(others) > 0
    n, at = len(found), np.flatnonzero(ends)
    columns = {
        "a": [max(ids[x], ids[y]) for x, y in found] + list(ids[at]), "b": [min(ids[x], ids[y]) for x, y in found] + [None] * len(at),
        "key": [None] * n + [key[0].as_py()] * len(at), "side": [None] * n + side[at].tolist(), "n": [None] * n + list(sizes[at]),
    }
    return pa.table({k: pa.array(v, pa.bool_() if k == "side" else pa.int64()) for k, v in columns.items()})


def compare_whole(rows: pa.Table, similarity: float) -> pa.Table:
    """a, b: a forest of the links between the rows with ``side`` and those without it, by all their hashes (``whole``,
    each once); a > b. Rows of one ``part`` are linked already."""
    side, ids = np.array(rows["side"], bool), np.array(rows["doc_id"], np.int64)
    tree = np.unique(np.array(rows["part"], np.int64), return_inverse=True)[1]
    whole = rows["whole"].combine_chunks()
    flat, sizes = np.asarray(whole.flatten()), np.array(whole.value_lengths(), np.int64)
    starts = np.cumsum(sizes) - sizes
    xs, ys = np.flatnonzero(side), np.flatnonzero(~side)
    found = []
    if len(xs) and len(ys):
        # For each hash the texts that have it, one after another.
        theirs = np.concatenate([flat[starts[y] : starts[y] + sizes[y]] for y in ys])
        order = np.argsort(theirs, kind="stable")
        owner = np.repeat(np.arange(len(ys)), sizes[ys])[order]
        known, first, counts = np.unique(theirs[order], return_index=True, return_counts=True)
        for x in xs:
            if (tree[ys] == tree[x]).all():
                continue
            at = np.flatnonzero(np.isin(known, flat[starts[x] : starts[x] + sizes[x]], assume_unique=True))
            n = counts[at]
            places = np.repeat(first[at] - (np.cumsum(n) - n), n) + np.arange(n.sum())
            shared = np.bincount(owner[places], minlength=len(ys))
            found.extend(join_trees(tree, x, ys[shared >= similarity * (sizes[x] + sizes[ys] - shared) - 1e-9]))
    got = [[top(ids[x], ids[y]) for x, y in found] for top in (max, min)]
    return pa.table([pa.array(x, pa.int64()) for x in got], names=["a", "b"])


def sketches(docs: DataFrame, id_col: str, text_col: str, words: int) -> DataFrame:
    """Per row of ``docs``: doc_id, th (text hash), fp, keys, n (shingles), low (the least hashes)."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            fps, keys, sizes, low = [], [], [], []
            for x in batch.column(1):
                h = shingle_hashes(x.as_buffer().to_pybytes(), words)
                fps.append(int(majority(h, np.zeros(1, np.int64))[0]) if len(h) else 0)
                keys.append(class_keys(h).view(np.int64))
                sizes.append(len(h))
                low.append(np.unique((h >> np.uint64(32)).astype("<u4"))[:SKETCH].tobytes())
            columns = [pa.array(np.array(fps, np.uint64).view(np.int64)), pa.array(keys, pa.list_(pa.int64())), pa.array(sizes, pa.int64()), pa.array(low, pa.binary())]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), *columns], names=["doc_id", "th", "fp", "keys", "n", "low"])

    return id_text(docs, id_col, text_col).withColumn("th", text_hash()).mapInArrow(work, "doc_id long, th long, fp long, keys array<long>, n long, low binary")


def all_hashes(docs: DataFrame, wanted: DataFrame, ws: Workspace, id_col: str, text_col: str, words: int) -> DataFrame:
    """v, whole: all shingle hashes (32 bits of each) of the texts of ``wanted``: doc_id, th, v."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k, x in enumerate(batch.column(1)):  # a text at a time, as they are long
                h = np.unique((shingle_hashes(x.as_buffer().to_pybytes(), words) >> np.uint64(32)).astype("<u4"))
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(k, 1), pa.array([h.view("<i4")], pa.list_(pa.int32()))], names=["v", "whole"])

    wanted = ws.save(wanted.select(F.col("doc_id").alias("w_id"), F.col("th").alias("w_th"), "v").distinct(), "wanted")
    texts = id_text(docs, id_col, text_col).withColumn("th", text_hash())
    met = texts.join(wanted, texts["doc_id"].eqNullSafe(wanted["w_id"]) & (texts["th"] == wanted["w_th"]))
    # Rows that repeat an id and text have equal hashes.
    return ws.save(met.select("v", "text").mapInArrow(work, "v long, whole array<int>"), "whole").dropDuplicates(["v"])


def vertices(each: DataFrame, ws: Workspace) -> DataFrame:
    """``each`` with v, one number for each id and text, in the order of the ids and then text hashes, null ids last.

    The ids themselves serve where none is null and none has two texts; else the texts' ids and hashes are sorted.
    """
    texts = ws.save(each.select("doc_id", "th").distinct(), "texts")
    if not texts.groupBy("doc_id").agg(F.count(F.lit(1)).alias("n")).where("n > 1 or doc_id is null").limit(1).count():
        return each.withColumn("v", F.col("doc_id"))
    ranked = texts.orderBy(F.col("doc_id").asc_nulls_last(), "th").select(F.col("doc_id").alias("r_id"), F.col("th").alias("r_th"), F.monotonically_increasing_id().alias("v"))
    ranked = ws.save(ranked, "ranked")
    return ws.save(each.join(ranked, F.col("doc_id").eqNullSafe(F.col("r_id")) & (F.col("th") == F.col("r_th"))).drop("r_id", "r_th"), "vertices")


def _met(x: DataFrame, y: DataFrame, known: DataFrame, ws: Workspace, judge: Callable, returns: str, deal: bool) -> DataFrame:
    """What ``judge`` says of the members ``x`` and ``y`` (key, doc_id, part) of the same buckets, with the columns of ``known``.

    Both sides of a bucket are split into blocks of about BLOCK documents, and of about VOLUME hashes where ``x`` and ``y``
    tell their ``n``, by the hash of the id; each block of one side meets each of the other in a task of its own, so that
    no pair is ever a row and a hot bucket is spread over tasks.
    """
    wide = F.ceil(F.count(F.lit(1)) / BLOCK)
    if "n" in x.columns:
        wide = F.greatest(wide, F.ceil(F.sum("n") / VOLUME))
    many = ws.save(x.groupBy("key").agg(wide.alias("bx")).join(y.groupBy("key").agg(wide.alias("by")), "key"), "blocks")
    own = lambda blocks: F.pmod(F.xxhash64("doc_id"), F.col(blocks))
    each = lambda blocks: F.explode(F.sequence(F.lit(0).cast("long"), F.col(blocks) - 1))
    left = x.join(many, "key").select("key", "doc_id", "part", F.lit(True).alias("side"), own("bx").alias("i"), each("by").alias("j"))
    right = y.join(many, "key").select("key", "doc_id", "part", F.lit(False).alias("side"), each("bx").alias("i"), own("by").alias("j"))
    rows = ws.save(left.unionByName(right), "rows")
    rows = known.join(rows.hint("shuffle_hash") if deal else rows, "doc_id").select("key", "i", "j", "side", "doc_id", "part", *(c for c in known.columns if c != "doc_id"))
    return ws.save(rows.groupBy("key", "i", "j").applyInArrow(judge, returns), "links")


def similar_links(each: DataFrame, ws: Workspace, similarity: float, whole_of: Callable[[DataFrame], DataFrame] | None = None) -> DataFrame:
    """(a, b) with a > b: documents that share the SimHash of a class, and whose similarity is high enough.

    The components of these links are those of all similar pairs that share a bucket; not every such pair is a link.
    Sketches tell most similarities; those within MARGIN of the threshold come from all hashes of the two texts, which
    ``whole_of`` gives (doc_id, whole) for some ids; without it they are left out.

    Of buckets with the same members one is kept. The members of a bucket larger than a block first meet HEADS of its
    members, which joins most copies at a cost in proportion. Then the members outside a bucket's largest component
    meet all of the bucket. Last, the ends of unsure pairs of a bucket meet once more with all their hashes. Only a bucket
    of many unlike documents comes to the square of its size, in worker memory.
    """
    judge = lambda key, t: compare(key, t, similarity)
    returns = "a long, b long, key long, side boolean, n long"

    def exactly(doubt: DataFrame, sure: DataFrame) -> DataFrame:
        roots = connected(sure, ws).select(F.col("v").alias("doc_id"), "root")
        doubt = doubt.select("key", "side", F.col("a").alias("doc_id"), "n").distinct().join(roots, "doc_id", "left")
        doubt = ws.save(doubt.select("key", "side", "doc_id", "n", F.coalesce("root", "doc_id").alias("part")), "doubt")
        apart = ws.save(doubt.groupBy("key").agg(F.min("part").alias("p"), F.max("part").alias("q")).where("p < q").select("key"), "apart")
        doubt = ws.save(doubt.join(apart, "key"), "doubt")
        ends = lambda side: doubt.where(side).select("key", "doc_id", "part", "n")
        return _met(ends("side"), ends("not side"), whole_of(doubt.select("doc_id").distinct()), ws, lambda t: compare_whole(t, similarity), "a long, b long", True)

    known = each.where("doc_id is not null").select("doc_id", "n", "low")
    if known.groupBy("doc_id").agg(F.count(F.lit(1)).alias("rows")).where("rows > 1").limit(1).count():
        # A document is one vertex however many rows repeat it; its rows agree in all columns.
        known = ws.save(known.dropDuplicates(["doc_id"]), "known")
    dealt = ws.save(each.where("doc_id is not null").select("doc_id", F.explode("keys").alias("key")).distinct(), "dealt")
    sets = dealt.groupBy("key").agg(F.count(F.lit(1)).alias("size"), F.bit_xor(F.xxhash64("doc_id")).alias("s"), F.bit_xor(F.xxhash64("doc_id", F.lit(1))).alias("t"))
    # Saved, here and below, so that the join does not keep the grouping's partitions: a hot key can be split over tasks.
    shared = ws.save(sets.where("size > 1").groupBy("size", "s", "t").agg(F.min("key").alias("key")).select("key", "size"), "shared")
    members = ws.save(dealt.join(shared, "key"), "members")
    ws.drop(dealt)
    hot = members.where(F.col("size") > BLOCK).select("key", "doc_id", F.col("doc_id").alias("part"))
    heads = hot.groupBy("key", F.pmod(F.xxhash64("doc_id"), F.lit(HEADS)).alias("k")).agg(F.min("doc_id").alias("doc_id"))
    first = _met(heads.select("key", "doc_id", F.col("doc_id").alias("part")), hot, known, ws, judge, returns, False)
    first = first.where("b is not null").select("a", "b")  # an unsure pair meets again below, or is joined by others
    roots = connected(first, ws)
    placed = members.join(roots.select(F.col("v").alias("doc_id"), "root"), "doc_id", "left").select("key", "doc_id", F.coalesce("root", "doc_id").alias("part"))
    placed = ws.save(placed, "placed")
    parts = placed.groupBy("key", "part").agg(F.count(F.lit(1)).alias("size"))
    mixed = parts.groupBy("key").agg(F.max(F.struct("size", "part"))["part"].alias("main"), F.count(F.lit(1)).alias("parts")).where("parts > 1").select("key", "main")
    mixed = ws.save(placed.join(ws.save(mixed, "main"), "key"), "mixed")
    rest = _met(mixed.where("part <> main").select("key", "doc_id", "part"), mixed.select("key", "doc_id", "part"), known, ws, judge, returns, True)
    sure = first.unionByName(rest.where("b is not null").select("a", "b"))
    doubt = rest.where("b is null")
    return sure if whole_of is None or doubt.isEmpty() else sure.unionByName(exactly(doubt, sure))


def drop_near_copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = 5, radius: int = 2, similarity: float = 0.8) -> DataFrame:
    """The rows of ``docs`` but for those that a near copy with a smaller doc_id stands for, with all their columns.

    Documents are linked when the SimHashes of their ``words``-word shingles differ in ``radius`` bits or fewer,
    found by covering masks without a miss, or when the Jaccard similarity of these shingles is ``similarity`` or
    more among documents that share the SimHash of a class of shingles. At 64 bits a similarity of 0.8 is about ten
    differing bits, for which no covering is small enough: hence the classes. Of each component the least doc_id
    stays. Documents without words are copies of each other. Rows without an id come after all others, by their
    text hash, as do the texts of one id among themselves.
    """
    ws = Workspace(docs.sparkSession, "near")
    each = vertices(ws.save(sketches(docs, id_col, text_col, words), "sketches"), ws)
    same = ws.save(each.groupBy("fp").agg(F.min("v").alias("least"), F.count(F.lit(1)).alias("n")), "distinct")
    links = fingerprint_links(same.select("fp"), ws, radius)
    least = lambda name: same.select(F.col("fp").alias(name), F.col("least").alias(f"{name}_id"))
    across = links.join(least("a"), "a").join(least("b"), "b").select(F.col("a_id").alias("a"), F.col("b_id").alias("b"))
    within = each.select("fp", F.col("v").alias("a")).join(same.where("n > 1").select("fp", F.col("least").alias("b")), "fp").select("a", "b")
    
    def whole_of(ids: DataFrame) -> DataFrame:
        wanted = each.select("doc_id", "th", "v").join(ids.withColumnRenamed("doc_id", "v"), "v", "left_semi")
        return all_hashes(docs, wanted, ws, id_col, text_col, words).withColumnRenamed("v", "doc_id")

    alike = similar_links(each.select(F.col("v").alias("doc_id"), "keys", "n", "low"), ws, similarity, whole_of)
    edges = across.unionByName(within).unionByName(alike)
    gone = connected(edges, ws).select("v").distinct()
    return drop_rows(docs, each.select("doc_id", "th", "v").join(gone, "v"), ws, id_col, text_col)


def op4_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    """simhash_groups() of ``documents`` at two bits, over shingles of three words."""
    out = simhash_groups(table(spark, sf_dir, "documents"))
    return out.select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")
