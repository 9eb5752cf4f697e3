"""Order MinHash fingerprints: text sketches that follow edit distance, not only the set of k-mers.

For each of ``sketches`` hash functions the ``picks`` smallest occurrence-numbered k-mers of a text are selected (the second
``abc`` of a text differs from the first), kept in text order and hashed as a tuple. Two texts agree on a tuple only if they
share its k-mers in that order; the share of equal tuples is the likeness of two fingerprints.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from dagframe.llm.common import partitions_of, read_table

K = 8
PICKS = 2
SKETCHES = 32
BLOCK = 1 << 16

_MIX = np.uint64(0x9E3779B97F4A7C15)
_TOP = np.uint64(0xFFFFFFFFFFFFFFFF)


def _scrambled(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def _multipliers(n: int) -> np.ndarray:
    return _scrambled(np.arange(1, n + 1, dtype=np.uint64) * _MIX) | np.uint64(1)


def numbered_kmers(text: str, k: int = K) -> np.ndarray:
    """A 64-bit value for every k-mer of ``text`` with the number of its occurrence; a shorter text is one k-mer."""
    points = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), dtype=np.uint32).astype(np.uint64)
    if not len(points):
        return points
    width = min(k, len(points))
    own = np.full(len(points) - width + 1, width, dtype=np.uint64)
    for i in range(width):
        own *= np.uint64(0x100000001B3)
        own += points[i : i + len(own)]
    own = _scrambled(own)
    order = np.argsort(own)
    ranked = own[order]
    same = ranked[1:] == ranked[:-1]
    if same.any():  # only values that repeat need their occurrences, which count in text order
        again = np.zeros(len(own), dtype=bool)
        again[1:] = same
        again[:-1] |= same
        at = np.sort(order[again])
        at = at[np.argsort(own[at], kind="stable")]
        group = own[at]
        first = np.flatnonzero(np.r_[True, group[1:] != group[:-1]])
        nth = np.arange(len(at)) - np.repeat(first, np.diff(np.r_[first, len(at)]))
        own[at] = _scrambled(own[at] + nth.astype(np.uint64) * _MIX)
    return own


def sketch(text: str, k: int = K, picks: int = PICKS, sketches: int = SKETCHES) -> np.ndarray:
    """``sketches`` 32-bit tuple hashes; an empty text has its own ones, all zero."""
    own = numbered_kmers(text, k)
    if not len(own):
        return np.zeros(sketches, dtype=np.uint32)
    factors, picks, block = _multipliers(sketches), min(picks, len(own)), max(1, BLOCK // len(own))
    chosen = np.empty((sketches, picks), dtype=np.int64)
    for j in range(0, sketches, block):
        values = factors[j : j + block, None] * own[None, :]
        rows = np.arange(len(values))
        for p in range(picks):
            at = values.argmin(axis=1)
            chosen[j : j + block, p] = at
            values[rows, at] = _TOP
    out = np.zeros(sketches, dtype=np.uint64)
    for at in np.sort(chosen, axis=1).T:
        out = _scrambled(out * np.uint64(0x100000001B3) ^ own[at])
    return (out >> np.uint64(32)).astype(np.uint32)


def as_text(values: np.ndarray) -> str:
    return values.astype(">u4").tobytes().hex()


def likeness(a: np.ndarray, b: np.ndarray) -> float:
    return float((a == b).mean())


def edited(text: str, following: str) -> str:
    """``text`` with its last third replaced by as much of the beginning of ``following``."""
    n = len(text) // 3
    return text[: len(text) - n] + following[:n]


def _with_next(docs: DataFrame, doc_id: str, text: str) -> tuple[DataFrame, int]:
    """Rows in ``parts`` ranges of falling ids, each range closed by a copy (``guest``) of the first row of the next one.

    Only that copy of one row per range crosses a border; the texts move once. Order: id falling, null last, then text
    falling. The last range is closed by the first row of all.
    """
    spark = docs.sparkSession
    parts = partitions_of(spark)
    rows = docs.select(F.col(doc_id).alias("doc_id"), F.coalesce(F.col(text), F.lit("")).alias("t"))
    cuts = sorted(set(rows.where("doc_id is not null").approxQuantile("doc_id", [i / parts for i in range(1, parts)], 0.2 / parts)), reverse=True) if parts > 1 else []
    bounds = F.array(*[F.lit(c) for c in cuts]) if cuts else F.array().cast("array<double>")
    part = F.when(F.col("doc_id").isNull(), F.lit(len(cuts))).otherwise(F.size(F.filter(bounds, lambda c: c > F.col("doc_id").cast("double"))))
    placed = rows.withColumn("part", part.cast("int"))
    firsts = {r["part"]: r["top"] for r in placed.groupBy("part").agg(F.max("doc_id").alias("top")).collect()}  # one row a range
    if not firsts:
        return placed.withColumn("guest", F.lit(False)), 1
    own = sorted(firsts)
    follows = {firsts[after]: before for before, after in zip(own, own[1:] + own[:1], strict=True)}  # id -> the range it closes
    targets = spark.createDataFrame([(i, p) for i, p in follows.items()], f"top_ {rows.schema['doc_id'].dataType.simpleString()}, to_ int")
    heads = rows.join(F.broadcast(targets), F.col("doc_id").eqNullSafe(F.col("top_")))
    guests = heads.groupBy("to_", "doc_id").agg(F.max("t").alias("t")).select("doc_id", "t", F.col("to_").alias("part"), F.lit(True).alias("guest"))
    return placed.withColumn("guest", F.lit(False)).unionByName(guests), len(cuts) + 1


def fingerprint_with_next(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", k: int = K, picks: int = PICKS, sketches: int = SKETCHES) -> DataFrame:
    """Fingerprints of every text and of its edited text, and their likenesses.

    The next document is the one with the next smaller id (after the last: the first). Null texts are empty. Rows with a null
    id come last; rows that repeat an id follow each other by text. A table of one row is its own next.
    """
    rows, parts = _with_next(docs, doc_id, text)
    kind = rows.schema["doc_id"].dataType.simpleString()
    dealt = rows.repartitionById(parts, "part").sortWithinPartitions("part", "guest", F.desc_nulls_last("doc_id"), F.desc("t"))

    def finished(own: tuple, following: tuple) -> tuple:
        new = edited(own[1], following[1])
        other = own[2] if new == own[1] else sketch(new, k, picks, sketches)
        return own[0], len(own[1]), hashlib.sha256(new.encode("utf-8", "surrogatepass")).hexdigest(), as_text(own[2]), as_text(other), likeness(own[2], other), likeness(own[2], following[2])

    def run(batches) -> Iterator[pa.RecordBatch]:
        before, part = None, None
        for b in batches:
            out = []
            for i, t, p, guest in zip(*(b.column(c).to_pylist() for c in ("doc_id", "t", "part", "guest")), strict=True):
                now = (i, t, before[2] if before is not None and before[1] == t else sketch(t, k, picks, sketches))
                if before is not None and p == part:
                    out.append(finished(before, now))
                before, part = (None, None) if guest else (now, p)
            columns = list(zip(*out, strict=True)) or [()] * 7
            kinds = [b.schema.field("doc_id").type, pa.int64(), pa.string(), pa.string(), pa.string(), pa.float64(), pa.float64()]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, kinds, strict=True)], ["doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next"])

    return dealt.mapInArrow(run, f"doc_id {kind}, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double")


def op9_order_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Order MinHash of every document and of its edited text."""
    return fingerprint_with_next(read_table(spark, sf_dir, "documents"))
