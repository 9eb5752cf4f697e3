"""Quality scores: logistic regression over hashed word n-grams, trained with follow-the-regularised-leader updates.

A text is a sequence of words and runs of punctuation. Features are the hashed n-grams (one and two) of three views of it: the
words themselves, their shapes (lower, title, upper, mixed, digits, the punctuation run), and whether each repeats the word
before it. Each feature's value is its share of the text's n-grams, so a score doesn't depend on length. Scoring is a sparse
dot product with the weights, which have a fixed size and are sent to all tasks.

Learning uses a bounded sample of labelled rows, ``sample`` (default 8,000) of those with the smallest hash of their id, as far
as their features together stay within ``most_features`` (default 16 million); every text is scored whole. Labels, languages, sources and ids never enter a score.
"""

from __future__ import annotations

import re
import zlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from dagframe.llm.common import read_table, release

BITS = 20
SAMPLE = 8000
EPOCHS = 3
MOST_FEATURES = 16_000_000
THRESHOLD = 0.7
SLICE = 1 << 18

_WORDS = re.compile(r"\w+|[^\w\s]+")


class _Ids(dict):
    """From word to (hash, shape hash) in one 64-bit number; a worker's cache, begun anew when it is full."""

    def __missing__(self, word: str) -> int:
        if len(self) > 250_000:
            self.clear()
        if word.isupper():
            shape = b"U" if len(word) > 1 else b"u"
        elif word.islower():
            shape = b"l"
        elif word.istitle():
            shape = b"T"
        elif word.isdigit():
            shape = b"9"
        elif word[0].isalnum() or word[0] == "_":
            shape = b"m"
        else:
            shape = b"p" + word[:3].encode("utf-8", "surrogatepass")
        made = zlib.crc32(word.encode("utf-8", "surrogatepass")) << 32 | zlib.crc32(shape)
        self[word] = made
        return made


_ids = _Ids()


def _pairs(x: np.ndarray, salt: int) -> np.ndarray:
    y = x.astype(np.uint64)
    return ((y[:-1] * np.uint64(0x9E3779B1) + y[1:] * np.uint64(0x85EBCA77) + np.uint64(salt)) >> np.uint64(7)).astype(np.uint32)


def feature_slices(text: str, bits: int = BITS):
    """Arrays of feature numbers of a text, slice by slice; n-grams reach over the borders of slices."""
    mask, last = np.uint32((1 << bits) - 1), None
    found = _WORDS.finditer(text) if len(text) > SLICE else None
    while True:
        words = _WORDS.findall(text) if found is None else [m.group() for _, m in zip(range(SLICE // 4), found, strict=False)]
        if not words:
            return
        both = np.fromiter(map(_ids.__getitem__, words), dtype=np.uint64, count=len(words))
        if last is not None:
            both = np.r_[last, both]
        own, shape = (both >> np.uint64(32)).astype(np.uint32), both.astype(np.uint32)
        same = (own[1:] == own[:-1]).astype(np.uint32)
        new = slice(0 if last is None else 1, None)
        yield np.concatenate([own[new], _pairs(own, 1), shape[new] * np.uint32(31) + np.uint32(7), _pairs(shape, 2), same * np.uint32(0x5BD1) + np.uint32(0xABCDE), _pairs(same + np.uint32(5), 3)]) & mask
        last = both[-1:]
        if found is None:
            return


def features(text: str, bits: int = BITS) -> tuple[np.ndarray, np.ndarray]:
    """Distinct feature numbers of a text and their shares."""
    parts = list(feature_slices(text, bits))
    if not parts:
        return np.zeros(0, dtype=np.uint32), np.zeros(0)
    keys, n = np.unique(np.concatenate(parts), return_counts=True)
    return keys, n / n.sum()


@dataclass
class Model:
    """Weights of all hashed features and the bias."""

    weights: np.ndarray
    bias: float

    def score(self, text: str) -> float:
        total, n = 0.0, 0
        for part in feature_slices(text, int(len(self.weights)).bit_length() - 1):
            total += float(self.weights[part].sum(dtype=np.float64))
            n += len(part)
        z = self.bias + (total / n if n else 0.0)
        return float(1 / (1 + np.exp(-np.clip(z, -35, 35))))


def train(rows: list[tuple[np.ndarray, np.ndarray, int]], bits: int = BITS, epochs: int = EPOCHS, alpha: float = 2.0, beta: float = 1.0, l1: float = 1e-4, l2: float = 1e-4) -> Model:
    """Follow-the-regularised-leader with one learning rate per feature; classes weigh the same in sum.

    ``rows``: (feature numbers, shares, label 0 or 1), learnt in the order given. Without rows, or with one class only, the
    model is the bias of that class's share.
    """
    size = 1 << bits
    z, n, w = np.zeros(size + 1), np.zeros(size + 1), np.zeros(size + 1)
    good = sum(y for *_, y in rows)
    if good in (0, len(rows)):
        return Model(np.zeros(size, dtype=np.float32), 0.0 if not rows else 5.0 if good else -5.0)
    for _ in range(epochs):
        for keys, share, y in rows:
            at = np.append(keys.astype(np.int64), size)
            x = np.append(share, 0.1).astype(float)
            zi, ni = z[at], n[at]
            wi = np.where(np.abs(zi) <= l1, 0.0, -(zi - np.sign(zi) * l1) / ((beta + np.sqrt(ni)) / (alpha * 50) + l2))
            p = 1 / (1 + np.exp(-np.clip(wi @ x, -35, 35)))
            g = (p - y) * x * (len(rows) / 2 / (good if y else len(rows) - good))
            z[at] = zi + g - (np.sqrt(ni + g * g) - np.sqrt(ni)) / (alpha * 50) * wi
            n[at] = ni + g * g
            w[at] = wi
    live = (np.abs(z) > l1) & (n > 0)
    w = np.where(live, -(z - np.sign(z) * l1) / ((beta + np.sqrt(n)) / (alpha * 50) + l2), 0.0)
    return Model(w[:size].astype(np.float32), float(w[size] * 0.1))


def remainder(doc_id: Column) -> Column:
    """crc32 of the id as text, modulo 4."""
    return F.pmod(F.crc32(doc_id.cast("string").cast("binary")), F.lit(4))


def learnt(docs: DataFrame, labels: DataFrame, doc_id: str = "doc_id", text: str = "text", label: str = "quality", sample: int = SAMPLE, bits: int = BITS, most_features: int = MOST_FEATURES) -> Model:
    """A model of the labelled rows whose id's remainder isn't 2; conflicting labels of one id count as their largest.

    It is learnt in one task from at most ``sample`` rows that have no more than ``most_features`` features together; the driver
    gets the weights alone, whose number is fixed.
    """
    known = labels.where(F.col(doc_id).isNotNull() & F.col(label).isNotNull() & (remainder(F.col(doc_id)) != 2))
    known = known.groupBy(F.col(doc_id).alias("id_")).agg(F.max(F.col(label).cast("int")).alias("y_"))
    chosen = known.orderBy(F.xxhash64("id_"), "id_").limit(sample)  # the documented bound on what is learnt from
    rows = docs.select(F.col(doc_id).alias("id_"), F.coalesce(F.col(text), F.lit("")).alias("t_")).join(F.broadcast(chosen), "id_")

    def run(batches):
        for b in (whole.slice(i, 50) for whole in batches for i in range(0, len(whole), 50)):
            made = [features(t, bits) for t in b.column(0).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(2), b.column(1), pa.array([k.astype("<u4").tobytes() for k, _ in made], pa.binary()), pa.array([s.astype("<f4").tobytes() for _, s in made], pa.binary())], ["h", "y", "k", "s"])
        _ids.clear()
        release()

    def learn(batches):
        kept, room = [], most_features
        for b in batches:
            for y, k, s in zip(*(b.column(i).to_pylist() for i in (1, 2, 3)), strict=True):
                room -= len(k) // 4
                if room >= 0:
                    kept.append((np.frombuffer(k, "<u4"), np.frombuffer(s, "<f4"), y))
        model = train(kept, bits)
        live = np.flatnonzero(model.weights)
        yield pa.RecordBatch.from_arrays([pa.array([model.bias]), pa.array([live.astype("<u4").tobytes()], pa.binary()), pa.array([model.weights[live].astype("<f4").tobytes()], pa.binary())], ["bias", "at", "w"])
        del kept
        release()

    made = rows.select("t_", F.col("y_").cast("int"), F.xxhash64("id_", F.lit(1)).alias("h")).mapInArrow(run, "h long, y int, k binary, s binary")
    got = made.repartition(1).sortWithinPartitions("h", "k").mapInArrow(learn, "bias double, at binary, w binary").collect()  # one task, of a bounded sample
    if not got:
        return train([], bits)
    weights = np.zeros(1 << bits, dtype=np.float32)
    weights[np.frombuffer(got[0]["at"], "<u4")] = np.frombuffer(got[0]["w"], "<f4")
    return Model(weights, got[0]["bias"])


def scores(docs: DataFrame, model: Model, text: str = "text", out: str = "score") -> DataFrame:
    """``docs`` without its text, with the score of each row in ``out``; null and empty texts score the bias."""
    kept = [c for c in docs.columns if c != text]
    names = [f"k{i}" for i in range(len(kept))]
    slim = docs.select(*[F.col(f"`{c}`").alias(n) for c, n in zip(kept, names, strict=True)], F.coalesce(F.col(text), F.lit("")).alias("t"))
    kinds = "".join(f"`{f.name}` {f.dataType.simpleString()}, " for f in slim.schema.fields[:-1])
    held = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        for b in batches:
            got = [held.value.score(t) for t in b.column(len(kept)).to_pylist()]
            yield pa.RecordBatch.from_arrays([*b.columns[: len(kept)], pa.array(got, pa.float64())], [*names, "score_"])
        _ids.clear()
        release()

    return slim.mapInArrow(run, f"{kinds}score_ double").select(*[F.col(n).alias(c) for c, n in zip(kept, names, strict=True)], F.col("score_").alias(out))


def keep_good(docs: DataFrame, labels: DataFrame, doc_id: str = "doc_id", text: str = "text", threshold: float = THRESHOLD, **options) -> DataFrame:
    """The rows of ``docs``, all columns, whose score reaches ``threshold``."""
    model = learnt(docs, labels, doc_id, text, **options)
    held, kinds = docs.sparkSession.sparkContext.broadcast(model), docs.schema
    at = docs.columns.index(text)

    def run(batches):
        for b in batches:
            good = [held.value.score(t or "") >= threshold for t in b.column(at).to_pylist()]
            yield b.filter(pa.array(good, pa.bool_()))
        _ids.clear()
        release()

    return docs.mapInArrow(run, kinds)


def op4_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Score and decision for every document."""
    docs = read_table(spark, sf_dir, "documents").select("doc_id", "text")
    model = learnt(docs, read_table(spark, sf_dir, "labels"))
    got = scores(docs, model)
    return got.select("doc_id", (remainder(F.col("doc_id")) == 2).alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))
