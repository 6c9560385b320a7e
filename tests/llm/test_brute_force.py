"""The models, the battery and each pipeline stage against plain Python."""

import collections
import hashlib
import itertools
import math
import random
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
import public_tokenizers
from querymarks.llm import bpe, decontaminate, language_model, quality, secrets, simhash
from test_operators import brute_contaminated, frame, library, lower, words


# -- language model
def brute_model(rows):
    """log10 probabilities of all texts, by the counts, the left-out estimates and the expectation-maximisation in plain loops."""
    crc = lambda i: zlib.crc32(str(i).encode())
    train = [(i, t) for i, t in rows if crc(i) % 7 != 2]
    dev = [(i, t) for i, t in train if crc(i) // 7 % language_model.DEVELOP == 0]
    tokens = lambda t: [*words(t), b""]

    def counts(some):
        one, two = collections.Counter(), collections.Counter()
        for _, t in some:
            w = tokens(t)
            one.update(w)
            two.update(zip([b"", *w], w))
        return one, two

    (c1, c2), (d1, d2) = counts(train), counts(dev)
    n, types, m = sum(c1.values()), len(c1), sum(d1.values())
    bucket = lambda c: min(language_model.BUCKETS - 1, math.ceil(math.log2(c + 1)))
    events = []
    for (a, b), times in d2.items():
        context = c1[a] - d1[a]
        events.append((bucket(context), (c2[a, b] - d2[a, b]) / max(context, 1), (c1[b] - d1[b]) / max(1, n - m), times))
    mix = {k: language_model.START for k in range(language_model.BUCKETS)}
    for _ in range(language_model.ROUNDS):
        sums = collections.defaultdict(lambda: [0.0, 0.0, 0.0])
        for k, f2, f1, times in events:
            shares = [mix[k][0] * f2, mix[k][1] * f1, mix[k][2] / (types + 1)]
            for j in range(3):
                sums[k][j] += times * shares[j] / sum(shares)
        for k, s in sums.items():
            raised = [max(x / sum(s), language_model.LEAST_WEIGHT) for x in s]
            mix[k] = tuple(x / sum(raised) for x in raised)
    out = {}
    for i, t in rows:
        w = tokens(t)
        p = [(mix[bucket(c1[a])], c2[a, b] / max(c1[a], 1), c1[b] / n) for a, b in zip([b"", *w], w)]
        out[i] = sum(math.log10(k[0] * x + k[1] * y + k[2] / (types + 1)) for k, x, y in p)
    return out


@pytest.mark.parametrize("block", [1 << 23, 900])
def test_scores_of_the_language_model(spark, block):
    rng = random.Random(21)
    vocabulary = [f"v{int(rng.paretovariate(0.7))}" for _ in range(400)]
    rows = [(i, " ".join(rng.choice(vocabulary) for _ in range(rng.randint(0, 60)))) for i in range(150)]
    want = brute_model(rows)
    got = {r["doc_id"]: r["score"] for r in language_model.score_texts(frame(spark, rows), block=block).collect()}
    assert got.keys() == want.keys() and all(got[i] == pytest.approx(want[i], rel=1e-9) for i in want)


# -- quality classifier
def test_fit_of_the_classifier(spark):
    """Standardisation, normal equations and calibration on rows that the test holds itself."""
    rng = random.Random(22)
    texts = [" ".join(rng.choice(("alpha", "beta", "A1", "zz!", "the")) for _ in range(rng.randint(1, 80))) for _ in range(300)]
    stats = np.array([quality.statistics(t.encode()) for t in texts])
    label = np.array([int(t.count("zz") * 6 < len(t.split())) for t in texts])
    rows = frame(spark, [(i, [float(x) for x in s], int(y)) for i, (s, y) in enumerate(zip(stats, label))], "doc_id long, stats array<double>, label int")
    model = quality.fit(rows)
    plain = quality.Model(stats.mean(0), np.maximum(stats.std(0), 1e-6))
    assert np.allclose(model.mean, plain.mean) and np.allclose(model.scale, plain.scale)
    fold = np.array([zlib.crc32(f"fold{i}".encode()) % 3 == 0 for i in range(len(texts))])
    x = plain.design(stats[~fold])
    ridge = np.linalg.solve(x.T @ x / len(x) + quality.PENALTY * np.eye(x.shape[1]), x.T @ label[~fold] / len(x))
    assert np.allclose(x @ model.weights, x @ ridge, atol=1e-6)
    # The isotonic fit by its minimax formula over the bins of the held rows.
    bins = np.clip(np.floor((model.raw(stats[fold]) + 1) / 3 * quality.BINS), 0, quality.BINS - 1)
    means = [(label[fold][bins == b].sum(), (bins == b).sum()) for b in np.unique(bins)]
    mean = lambda a, b: sum(s for s, _ in means[a : b + 1]) / sum(n for _, n in means[a : b + 1])
    want = [max(min(mean(a, b) for b in range(k, len(means))) for a in range(k + 1)) for k in range(len(means))]
    assert np.allclose(model.values, want)


def test_features_approach_the_kernel():
    rng = np.random.default_rng(5)
    stats = rng.normal(size=(40, len(quality.STATISTICS)))
    model = quality.Model(np.zeros(stats.shape[1]), np.ones(stats.shape[1]), features=20_000)
    z = model.design(stats)[:, :20_000]
    gaps = ((stats[:, None] - stats[None]) ** 2).sum(-1)
    assert np.abs(z @ z.T - np.exp(-gaps / (2 * stats.shape[1]))).max() < 0.05


# -- secrets
ORDINARY = "get user account file path build release report year total config server client image video index data value name list page item order customer north".split()


def ordinary(rng):
    w = lambda: rng.choice(ORDINARY)
    return rng.choice((
        lambda: "_".join(w() for _ in range(rng.randint(3, 6))) + f"_{rng.randint(1, 99999)}", lambda: "".join(w().title() for _ in range(rng.randint(4, 7))) + str(rng.randint(1, 99)),
        lambda: "/".join([w(), str(rng.randint(1990, 2030)), f"{rng.randint(1, 12):02d}", *(w() for _ in range(rng.randint(2, 5)))]), lambda: "-".join(w() for _ in range(rng.randint(4, 6))) + f"-v{rng.randint(1, 20)}",
    ))()


def brute_battery(s):
    """(uniform, structured) with exact normal tails."""
    above = lambda z: math.erfc(z / math.sqrt(2)) / 2
    letters = next(a for p, a in secrets.ENCODINGS if __import__("re").match(p, s))
    at = [letters.index(c) + 1 for c in s]
    n, k = len(s), len(letters)
    chi = sum(v * v for v in collections.Counter(at).values()) * k / n - n
    df = k - 1
    ps = [above(((max(chi, 0) / df) ** (1 / 3) - (1 - 2 / (9 * df))) / math.sqrt(2 / (9 * df)))]
    mean = sum(at) / n
    d = [x - mean for x in at]
    runs = 1 + sum((a > 0) != (b > 0) for a, b in zip(d, d[1:]))
    high = sum(x > 0 for x in d)
    expected = 2 * high * (n - high) / n + 1
    ps.append(2 * above(abs((runs - expected) / math.sqrt(max((expected - 1) * (expected - 2) / (n - 1), 1e-9)))))
    ps.append(2 * above(abs((sum(a * b for a, b in zip(d, d[1:])) / max(sum(x * x for x in d), 1e-9) + 1 / n) * math.sqrt(n))))
    kind = lambda c: "0" if c.isdigit() else "A" if c.isupper() else "a" if c.islower() else "%"
    changes = sum(kind(a) != kind(b) and (kind(a), kind(b)) != ("A", "a") for a, b in zip(s, s[1:]))
    few = above((df + n * secrets.STRUCTURE - chi) / math.sqrt(2 * df + 4 * n * secrets.STRUCTURE))
    many = above((changes - 0.5 - (n - 1) * secrets.CHANGES) / math.sqrt((n - 1) * secrets.CHANGES * (1 - secrets.CHANGES)))
    both = max(few * many, 1e-300)
    return min(1.0, 3 * min(ps)), both * (1 - math.log(both))


def test_battery(spark):
    rng = random.Random(23)
    alphabets = [a for _, a in secrets.ENCODINGS]
    strings = [ordinary(rng) for _ in range(40)] + ["".join(rng.choice(a) for _ in range(rng.randint(20, 70))) for a in alphabets for _ in range(5)]
    strings = [s for s in strings if len(s) >= 20 and any(c.isdigit() for c in s)]
    got = frame(spark, [(i, s) for i, s in enumerate(strings)]).select("text", secrets._battery(F.col("text")).alias("t")).collect()
    for r in got:
        uniform, structured = brute_battery(r["text"])
        assert uniform * 0.9 <= r["t"]["uniform"] <= uniform * 1.1 + 1e-12, r["text"]
        assert structured * 0.8 <= r["t"]["structured"] <= structured * 1.2 + 1e-12, r["text"]


def test_planted_keys_are_found(spark):
    """Of random keys of 40 characters nine in ten or more, and few others among hundreds of ordinary strings."""
    rng = random.Random(24)
    base64 = secrets.ENCODINGS[7][1]
    rows, keys = [], {}
    for i in range(300):
        text = " ".join([rng.choice(ORDINARY), ordinary(rng), rng.choice(ORDINARY), ordinary(rng)])
        if i % 10 == 0:
            keys[i] = "".join(rng.choice(base64) for _ in range(40))
            text += " " + keys[i]
        rows.append((i, text))
    got = {r["doc_id"]: {rows[r["doc_id"]][1][x["start"] : x["end"]] for x in r["found"]} for r in secrets.scan(frame(spark, rows)).collect()}
    hits = sum(keys[i] in got[i] for i in keys)
    others = sum(len(x - {keys.get(i)}) for i, x in got.items())
    assert hits >= 0.9 * len(keys) and others <= 0.15 * max(1, hits)


def test_many_spans_and_long_runs(spark):
    text = "x" * 200_000 + " password=abcdefgh1" * 700 + " AKIA" + "B" * 20
    row = secrets.scan(frame(spark, [(1, text)])).first()
    assert len(row["base"]) == 701 and row["base"][700]["kind"] == "access"
    assert [(x["start"], x["end"]) for x in row["base"][:700]] == [(200_001 + 19 * k, 200_019 + 19 * k) for k in range(700)]


# -- pipeline, a stage at a time on the whole small tables
def brute_near(rows):
    """The documents that a component's least id stands for, over all pairs of fingerprints and shingle sets."""
    root = {i: i for i, _ in rows}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    held = {}
    for i, t in rows:
        w = words(t)
        held[i] = (frozenset(tuple(w[k : k + 5]) for k in range(len(w) - 4)) or frozenset([tuple(w)] if w else []), int(simhash.majority(h, np.zeros(1, np.int64))[0]) if len(h := simhash.shingle_hashes((t or "").encode())) else 0)
    for (a, (x, p)), (b, (y, q)) in itertools.combinations(held.items(), 2):
        if (p ^ q).bit_count() <= 2 or x and y and len(x & y) >= 0.8 * len(x | y):
            low, high = sorted((find(a), find(b)))
            root[high] = low
    return {i for i in root if find(i) == i}


def test_stages_against_brute_force(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    stages = dict(corpus_pipeline.STAGES)
    rows = {r["doc_id"]: r["text"] for r in docs.select("doc_id", "text").collect()}
    of = lambda df: {r["doc_id"] for r in df.select("doc_id").collect()}
    only = lambda ids: docs.where(F.col("doc_id").isin(*ids))
    labels = spark.read.parquet(f"{small}/labels.parquet")
    kept = of(stages["quality_classifier"](spark, docs, small))
    assert kept == {r["doc_id"] for r in quality.quality(docs, labels).collect() if r["score"] >= 0.7}
    last = {}
    for i in sorted(kept):
        last[lower(rows[i])] = i
    assert of(stages["exact_dedup"](spark, only(kept), small)) == set(last.values())
    kept = set(last.values())
    near = brute_near([(i, rows[i]) for i in sorted(kept)])
    assert of(stages["simhash_near_dedup"](spark, only(kept), small)) == near
    items = [r["text"] for r in spark.read.parquet(f"{small}/benchmark.parquet").collect()]
    short = {i for i in near if len(rows[i]) < 2500}
    clean = {i for i in short if not any(brute_contaminated(rows[i], t) for t in items)}
    assert clean < short and of(stages["benchmark_decontamination"](spark, only(short), small)) == clean
    own = bpe.codec(public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN)
    whole = library(own)
    for r in stages["byte_bpe"](spark, only(clean), small).collect():
        ids = np.array(whole.encode_ordinary(rows[r["doc_id"]]), "<u4")
        assert (r["n_tokens"], r["ids_sha256"]) == (len(ids), hashlib.sha256(ids.tobytes()).hexdigest())
        assert r["decoded_sha256"] == hashlib.sha256(rows[r["doc_id"]].encode()).hexdigest()


def test_a_benchmark_of_short_items_only(spark):
    bench = frame(spark, [(1, "alpha beta gamma delta epsilon")], "item_id long, text string")
    rows = [(1, "x alpha beta ZETA delta epsilon y"), (2, "alpha beta zeta delta eta")]
    assert [r["doc_id"] for r in decontaminate.contaminated(frame(spark, rows), bench).collect()] == [1]
