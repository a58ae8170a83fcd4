"""Quality classifier: hashed word n-gram logistic regression, trained with follow-the-regularised-leader updates.

A word is seen twice: as its letters, lower-cased, and as a shape (how it is cased, and the signs around it), in which
words never met before look like ones that were. Features are hashed unigrams and bigrams of the letters, unigrams, bigrams and
trigrams of the shapes, and bigrams of shapes whose words are equal; each family's counts are divided by its length, so a
score doesn't depend on how long a text is. Scoring is a sparse dot product per text.

Training uses about ``sample`` labelled rows at most, drawn by their ids' hash, and of their features about ``sample_bytes``. Features
are made where the rows lie; the updates run in one task over that bounded sample, in hash order, so that a repeated run gives the
same weights. The weights are
2**``bits`` floats, whatever the data.

Defined cases: a null text is empty and gets the score of the bias alone; rows without a label or an id aren't trained on;
a doc id that has several labels is trained on with each; with no labelled rows all scores are 0.5; an empty table gives no rows; other
columns are ignored.
"""

from __future__ import annotations

import functools
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import in_arrow, stage, whole_text

_FAMILIES = 6
_MIX = np.array([0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x27D4EB2F165667C5, 0x85EBCA77C2B2AE63, 0xD6E8FEB86659FD93], np.uint64)
#: Words that are remembered, and words that are looked at together.
_MOST, _PIECE = 60_000, 1 << 16


def _shape(word: str) -> tuple[str, str]:
    """The letters and digits of a word between its signs; and its casing with those signs."""
    core = word.strip("""!"#$%&'()*+,-./:;<=>?@[\\]^_`{|}~""")
    at = word.find(core) if core else len(word)
    case = "" if not core else "0" if core.isdigit() else "A" if core.isupper() and len(core) > 1 else "a" if core.islower() else "Aa" if core[:1].isupper() and core[1:] == core[1:].lower() else "*"
    return core.lower(), f"{word[:at][:4]}\x00{case}\x00{word[at + len(core) :][:4]}"


class Features:
    """Texts to hashed features."""

    def __init__(self, bits: int):
        self.shift = np.uint64(64 - bits)
        self._words: dict[str, tuple[int, int]] = {}

    def _hashes(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        known = self._words
        if len(known) > _MOST:
            known.clear()
        for word in set(words).difference(known):
            core, shape = _shape(word)
            known[word] = zlib.crc32(core.encode()) + 1, zlib.crc32(shape.encode()) + 1
        both = np.array([known[x] for x in words], np.uint64).reshape(-1, 2)
        return both[:, 0], both[:, 1]

    def forget(self) -> None:
        """Give the memory back: other work may follow in this worker."""
        self._words.clear()

    def places(self, text: str) -> Iterator[list[np.ndarray]]:
        """Per piece of the text: for each family, the places of its n-grams."""
        words = text.split()
        for at in range(0, len(words), _PIECE):
            part = words[max(0, at - 2) : at + _PIECE]
            letters, shapes = self._hashes(part)
            with np.errstate(over="ignore"):
                two, three = shapes[:-1] * np.uint64(31) + shapes[1:], shapes[:-2] * np.uint64(961) + shapes[1:-1] * np.uint64(31) + shapes[2:]
                again = letters[:-1] == letters[1:]
                families = [letters, letters[:-1] * np.uint64(0x100000001B3) + letters[1:], shapes, two, three, two * (~again).astype(np.uint64) + again.astype(np.uint64)]
                # What the piece before has had already.
                seen = [2, 1, 2, 1, 0, 1] if at else [0] * _FAMILIES
                yield [((x[s:] + np.uint64(1)) * m ^ (x[s:] >> np.uint64(29))) * _MIX[0] >> self.shift for x, s, m in zip(families, seen, _MIX, strict=True)]

    def sparse(self, text: str) -> tuple[np.ndarray, np.ndarray]:
        """Places and values of a text's features."""
        pieces = list(self.places(text))
        if not pieces:
            return np.zeros(0, np.int64), np.zeros(0)
        families = [np.concatenate(x) for x in zip(*pieces, strict=True)]
        place = np.concatenate(families).astype(np.int64)
        value = np.concatenate([np.full(len(x), 1 / max(len(x), 1)) for x in families])
        place, inverse = np.unique(place, return_inverse=True)
        return place, np.bincount(inverse, value)

    def dot(self, text: str, weights: np.ndarray) -> float:
        """The text's features times the weights."""
        total, count = np.zeros(_FAMILIES), np.zeros(_FAMILIES)
        for piece in self.places(text):
            for k, x in enumerate(piece):
                total[k] += weights[x].sum()
                count[k] += len(x)
        return float((total / np.maximum(count, 1)).sum())


@functools.lru_cache(maxsize=2)
def features_for(bits: int) -> Features:
    """A worker's features: later tasks find its words known."""
    return Features(bits)


class FollowTheLeader:
    """Logistic regression by follow-the-regularised-leader: per coordinate, the sum of gradients less what the weight already accounts for, and the sum of their squares."""

    def __init__(self, size: int, rate: float = 0.5, smooth: float = 1.0, sparse: float = 1e-4, ridge: float = 1e-4):
        self.z, self.n = np.zeros(size + 1), np.zeros(size + 1)  # the last is the bias
        self.rate, self.smooth, self.sparse, self.ridge = rate, smooth, sparse, ridge

    def weights(self, at=slice(None)) -> np.ndarray:
        z, n = self.z[at], self.n[at]
        return np.where(np.abs(z) <= self.sparse, 0.0, -(z - np.sign(z) * self.sparse) / ((self.smooth + np.sqrt(n)) / self.rate + self.ridge))

    def learn(self, place: np.ndarray, value: np.ndarray, label: float) -> None:
        at, x = np.append(place, len(self.z) - 1), np.append(value, 1.0)
        w = self.weights(at)
        gradient = (1 / (1 + np.exp(-np.clip(w @ x, -35, 35))) - label) * x
        squares = self.n[at] + gradient * gradient
        self.z[at] += gradient - (np.sqrt(squares) - np.sqrt(self.n[at])) / self.rate * w
        self.n[at] = squares


def fold(id_col: str | Column, folds: int = 5) -> Column:
    """crc32 of the id as text, modulo ``folds``."""
    return F.pmod(F.crc32((F.col(id_col) if isinstance(id_col, str) else id_col).cast("string").cast("binary")), F.lit(folds))


def train(docs: DataFrame, labels: DataFrame, label_col: str = "quality", folds: int = 5, bits: int = 18, sample: int = 16_000, sample_bytes: int = 256 << 20, rounds: int = 3, scale: float = 8.0) -> np.ndarray:
    """Weights, the bias last, from the labelled rows of ``docs`` (doc_id, text) outside fold 0: ``sample`` ids and ``sample_bytes`` of features, about, at most."""
    marked = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col(label_col).cast("int").alias("label"))
    marked = marked.filter("label is not null and doc_id is not null").filter(fold("doc_id", folds) != 0).distinct()
    n = marked.count()
    # A share of the ids' hash values, so that about ``sample`` rows stay however many there are. Hence the bound of what is broadcast.
    key = F.pmod(F.xxhash64(F.lit("sample"), "doc_id"), F.lit(1 << 30))
    drawn = F.broadcast(marked.filter(key < int((1 << 30) * min(1.0, sample / max(n, 1)))))
    drawn = docs.select(F.col("doc_id").cast("long").alias("doc_id"), whole_text("text").alias("text")).join(drawn, "doc_id")

    def features(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        made = features_for(bits)
        for batch in batches:
            sparse = [made.sparse(x.as_py()) for x in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), pa.array([p.astype("<i4").tobytes() for p, _ in sparse], pa.binary()), pa.array([v.astype("<f4").tobytes() for _, v in sparse], pa.binary())], names=["h", "label", "place", "value"])

    def learn(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = FollowTheLeader(1 << bits)
        rows = sorted((row for b in batches for row in zip(*(x.to_pylist() for x in b.columns), strict=True)), key=lambda x: (x[0], x[1], x[2]))
        for _ in range(rounds):
            for _, label, place, value in rows:
                model.learn(np.frombuffer(place, "<i4"), np.frombuffer(value, "<f4") * scale, float(label))
        if rows:
            yield pa.RecordBatch.from_pydict({"weights": [model.weights().astype("<f4").tobytes()]})

    rows = drawn.select(F.xxhash64("doc_id").alias("h"), "text", "label")
    rows = stage(in_arrow(rows, features, "h long, label int, place binary, value binary").withColumn("line", F.monotonically_increasing_id()), "features")
    size = rows.agg(F.sum(F.octet_length("place") + F.octet_length("value"))).first()[0] or 0
    if size > sample_bytes:
        rows = rows.filter(F.pmod(F.xxhash64(F.lit("bytes"), "h", "line"), F.lit(1 << 30)) < int((1 << 30) * sample_bytes / size))
    learnt = stage(rows.drop("line").coalesce(1).mapInArrow(learn, "weights binary"), "weights").collect()
    return np.frombuffer(learnt[0]["weights"], "<f4").astype(np.float64) if learnt else np.zeros((1 << bits) + 1)


def score(docs: DataFrame, weights: np.ndarray, scale: float = 8.0, id_col: str = "doc_id", text_col: str = "text", keep: list[str] | None = None) -> DataFrame:
    """Rows (doc_id, score), or ``keep``'s columns and score. Nothing is shuffled, and a text travels once."""
    bits = (len(weights) - 1).bit_length() - 1
    shared = docs.sparkSession.sparkContext.broadcast(weights)  # 2**bits floats
    own = keep is not None and text_col in keep and docs.schema[text_col].dataType.typeName() == "string"
    rows = docs.select(*([F.col(id_col).cast("long").alias("doc_id")] if keep is None else [F.col(f"`{x}`") for x in keep]), *([] if own else [whole_text(text_col).alias("__own_text")]))
    at = keep.index(text_col) if own else len(rows.columns) - 1

    def scores(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        made = features_for(bits)
        for batch in batches:
            sums = [scale * made.dot(x.as_py() or "", shared.value) + shared.value[-1] for x in batch.column(at)]
            found = pa.array(1 / (1 + np.exp(-np.clip(np.array(sums, np.float64), -35, 35))))
            kept = batch.columns if own else batch.columns[:-1]
            yield pa.RecordBatch.from_arrays([*kept, found], names=[*batch.schema.names[: len(kept)], "__own_score"])
        made.forget()

    schema = rows.drop("__own_text").withColumn("__own_score", F.lit(0.0)).schema
    return in_arrow(rows, scores, schema)


def quality_scores(docs: DataFrame, labels: DataFrame, threshold: float = 0.3, label_col: str = "quality", folds: int = 5) -> DataFrame:
    """Train on the labelled rows of ``docs`` outside fold 0, then score all: (doc_id, held_out, score, predicted)."""
    out = score(docs, train(docs, labels, label_col, folds))
    return out.select("doc_id", (fold("doc_id", folds) == 0).alias("held_out"), F.col("__own_score").alias("score"), (F.col("__own_score") >= threshold).cast("int").alias("predicted"))
