"""The classifier's features, scores and training, against plain Python that shares no code with them."""

import math
import string
import zlib

import numpy as np
import pytest

from subgraph_spark.llm import quality

MASK = (1 << 64) - 1
FACTORS = [0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x27D4EB2F165667C5, 0x85EBCA77C2B2AE63, 0xD6E8FEB86659FD93]


def slow_words(text):
    """Numbers for the letters and for the shape of each word."""
    out = []
    for word in text.split():
        core = word.strip(string.punctuation)
        before = word[: word.find(core)] if core else word
        behind = word[len(before) + len(core) :]
        if not core:
            case = ""
        elif core.isdigit():
            case = "0"
        elif core.isupper() and len(core) > 1:
            case = "A"
        elif core.islower():
            case = "a"
        elif core[0].isupper() and core[1:] == core[1:].lower():
            case = "Aa"
        else:
            case = "*"
        out.append((zlib.crc32(core.lower().encode()) + 1, zlib.crc32("\0".join((before[:4], case, behind[:4])).encode()) + 1))
    return out


def slow_features(text, bits):
    words = slow_words(text)
    families = [[] for _ in range(6)]
    for i, (letter, shape) in enumerate(words):
        families[0].append(letter)
        families[2].append(shape)
        if i + 1 < len(words):
            two = shape * 31 + words[i + 1][1]
            families[1].append(letter * 0x100000001B3 + words[i + 1][0])
            families[3].append(two)
            families[5].append(1 if letter == words[i + 1][0] else two)
        if i + 2 < len(words):
            families[4].append(shape * 961 + words[i + 1][1] * 31 + words[i + 2][1])
    out = {}
    for factor, family in zip(FACTORS, families, strict=True):
        for x in family:
            x &= MASK
            place = ((((x + 1) * factor & MASK) ^ x >> 29) * FACTORS[0] & MASK) >> 64 - bits
            out[place] = out.get(place, 0.0) + 1 / len(family)
    return out


TEXTS = ["", "one", "The cat, the CAT! the the 123 x-ray McDonald «ok» ...", "a b", "Ünï ünï 42 42 !!", " ".join(f"W{i % 9}ord{i % 4}, b{i}" for i in range(300))]


@pytest.mark.parametrize("text", TEXTS, ids=range(len(TEXTS)))
def test_features(text):
    place, value = quality.Features(14).sparse(text)
    expected = slow_features(text, 14)
    assert dict(zip(place.tolist(), value.tolist(), strict=True)) == pytest.approx(expected)
    weights = np.random.default_rng(3).standard_normal(1 << 14)
    assert quality.Features(14).dot(text, weights) == pytest.approx(sum(weights[k] * v for k, v in expected.items()))


def slow_training(rows, rounds, rate=0.5, smooth=1.0, sparse=1e-4, ridge=1e-4):
    """Follow-the-regularised-leader over (features with bias, label) by the textbook, in dictionaries."""
    z, n = {}, {}

    def weight(k):
        a = z.get(k, 0.0)
        return 0.0 if abs(a) <= sparse else -(a - math.copysign(sparse, a)) / ((smooth + math.sqrt(n.get(k, 0.0))) / rate + ridge)

    for _ in range(rounds):
        for x, label in rows:
            w = {k: weight(k) for k in x}
            p = 1 / (1 + math.exp(-sum(w[k] * v for k, v in x.items())))
            for k, v in x.items():
                g = (p - label) * v
                sigma = (math.sqrt(n.get(k, 0.0) + g * g) - math.sqrt(n.get(k, 0.0))) / rate
                z[k] = z.get(k, 0.0) + g - sigma * w[k]
                n[k] = n.get(k, 0.0) + g * g
    return {k: weight(k) for k in z}


def test_training_and_scores(spark):
    """A trained model's weights and the scores of all texts, those without a label and an empty one too."""
    texts = [f"Good prose, number {i}. It has sentences!" if i % 2 else f"BUY now $$ {i} buy now buy" for i in range(40)] + ["", "never seen words only"]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    labels = spark.createDataFrame([(i, i % 2) for i in range(40)], "doc_id long, quality int")
    got = quality.train(docs, labels, bits=12, rounds=2)
    learnt = [i for i in range(40) if zlib.crc32(str(i).encode()) % 5]
    order = {r.doc_id: r.h for r in docs.selectExpr("doc_id", "xxhash64(doc_id) AS h").collect()}
    single = lambda x: float(np.float32(x))
    rows = [({**{k: single(v) * 8.0 for k, v in slow_features(texts[i], 12).items()}, "bias": 1.0}, i % 2) for i in sorted(learnt, key=order.get)]
    expected = slow_training(rows, 2)
    assert got[-1] == pytest.approx(expected.pop("bias"), rel=1e-4)
    for k in range(1 << 12):
        assert got[k] == pytest.approx(expected.get(k, 0.0), rel=1e-4, abs=1e-6)
    scores = {r.doc_id: r["__own_score"] for r in quality.score(docs, got).collect()}
    for i, text in enumerate(texts):
        total = got[-1] + 8.0 * sum(got[k] * v for k, v in slow_features(text, 12).items())
        assert scores[i] == pytest.approx(1 / (1 + math.exp(-total)), rel=1e-9)


def test_bytes_of_the_sample_are_bounded(spark):
    """Long texts: a smaller share of the rows is learnt from, and the model still tells the classes apart."""
    texts = [(f"calm words {i} " if i % 2 else f"LOUD!! {i} ") * 400 for i in range(60)]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    labels = spark.createDataFrame([(i, i % 2) for i in range(60)], "doc_id long, quality int")
    weights = quality.train(docs, labels, sample_bytes=3_000)
    assert (weights != quality.train(docs, labels)).any()
    scores = {r.doc_id: r["__own_score"] for r in quality.score(docs, weights).collect()}
    assert np.mean([(scores[i] >= 0.5) == bool(i % 2) for i in range(60)]) > 0.9
