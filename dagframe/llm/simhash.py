"""SimHash near-dedup by anchor points.

A fingerprint is the bitwise majority of the XXH64 values of a text's word shingles. Two fingerprints that differ in at
most ``distance`` bits are found without comparing all pairs: the 64 bits are cut into segments, so that one segment of
the pair differs in at most ``distance // segments`` bits; on each segment a covering code (a Hamming code of 15 bits,
covering radius 1, beside free bits) supplies the anchors. Each fingerprint lives at the anchor that covers it and is
also sent to every anchor that covers a word within the segment's threshold (the anchors within radius plus threshold
that can matter). The residents of an anchor are compared with its visitors, on all 64 bits.

Equal fingerprints are one node from the start. An anchor gives a spanning forest of its links, never all pairs. An
anchor with far more rows than the mean is cut into a grid of cells, residents by rows, visitors by columns.
"""

from __future__ import annotations

from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from dagframe.llm.common import fresh, partitions_of, read_table, release, with_checkpoints
from dagframe.llm.components import components

SEED = 42
SHINGLE = 4
DISTANCE = 4
BLOCK = 1 << 15
MOST_IDS = 1_000_000


def fingerprint_bytes(text: bytes, shingle: int = SHINGLE) -> int:
    """The 64-bit SimHash of one UTF-8 text; 0 without words; one shingle of all words if there are too few."""
    words = text.lower().split()  # for bytes: A-Z and ASCII white space only
    if not words:
        return 0
    digest, ones, n = xxhash.xxh64_digest, np.zeros(64, dtype=np.int64), max(1, len(words) - shingle + 1)
    for at in range(0, n, BLOCK):
        end = min(n, at + BLOCK)
        parts = zip(*(words[at + k : end + k] for k in range(shingle)), strict=True) if len(words) >= shingle else [words]
        packed = b"".join([digest(b" ".join(p), SEED) for p in parts])
        ones += np.unpackbits(np.frombuffer(packed, dtype=np.uint8).reshape(-1, 8), axis=1).sum(axis=0, dtype=np.int64)
    return int.from_bytes(np.packbits(2 * ones > n).tobytes(), "big")


def fingerprints(docs: DataFrame, text: str = "text", out: str = "fp", shingle: int = SHINGLE) -> DataFrame:
    """``docs`` without its text, with the fingerprint as a signed long in ``out``; null texts count as empty."""
    kept = [c for c in docs.columns if c != text]
    names = [f"k{i}" for i in range(len(kept))]
    slim = docs.select(*[F.col(f"`{c}`").alias(n) for c, n in zip(kept, names, strict=True)], F.coalesce(F.col(text), F.lit("")).alias("t"))
    kinds = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in slim.schema.fields[:-1])

    def run(batches):
        for b in batches:
            values = [fingerprint_bytes(x, shingle) for x in b.column(len(kept)).cast(pa.binary()).to_pylist()]
            yield pa.RecordBatch.from_arrays([*b.columns[: len(kept)], pa.array(np.array(values, dtype=np.uint64).view(np.int64))], [*names, "fp_"])
        release()

    done = slim.mapInArrow(run, f"{kinds}{', ' if kinds else ''}fp_ long")
    return done.select(*[F.col(n).alias(c) for c, n in zip(kept, names, strict=True)], F.col("fp_").alias(out))


class AnchorPlan:
    """Segments of the 64 bits, each with a Hamming(15, 11) code beside free bits, and the words within the threshold."""

    def __init__(self, distance: int = DISTANCE, segments: int = 3):
        if not 0 <= distance < 64 or not 2 <= segments <= 4:
            raise ValueError("distance must be 0..63 and segments 2..4")
        self.distance, self.parts, at = distance, [], 0
        near = distance // segments
        for k in range(segments):
            width = (64 - at) // (segments - k)
            flips = [0] + [sum(1 << i for i in c) for w in range(1, near + 1) for c in combinations(range(width), w)]
            self.parts.append((at, width, np.array(flips, dtype=np.uint64)))
            at += width
        syndrome = np.zeros(1 << 15, dtype=np.uint16)
        words = np.arange(1 << 15)
        for bit in range(15):
            syndrome ^= np.where(words >> bit & 1, bit + 1, 0).astype(np.uint16)
        self.covered = (words ^ np.where(syndrome > 0, 1 << (syndrome.astype(np.int64) - 1), 0)).astype(np.uint64)

    def _anchor(self, word: np.ndarray, width: int) -> np.ndarray:
        if width < 15:
            return word
        low = word & np.uint64(0x7FFF)
        return word >> np.uint64(15) << np.uint64(15) | self.covered[low.astype(np.int64)]

    def rows(self, fp: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(anchor, fingerprint, resident?) of all places that fingerprints go to."""
        keys, owners, home = [], [], []
        for k, (at, width, flips) in enumerate(self.parts):
            word = fp >> np.uint64(at) & np.uint64((1 << width) - 1)
            own = self._anchor(word, width)
            all_ = np.sort(self._anchor(word[:, None] ^ flips[None, :], width), axis=1)
            new = np.ones(all_.shape, dtype=bool)
            new[:, 1:] = all_[:, 1:] != all_[:, :-1]
            r, c = np.nonzero(new)
            key = all_[r, c]
            keys.append(key | np.uint64(k << 60))
            owners.append(fp[r])
            home.append(key == own[r])
        return np.concatenate(keys), np.concatenate(owners), np.concatenate(home)


def _forest(x: np.ndarray, y: np.ndarray, distance: int) -> tuple[np.ndarray, np.ndarray]:
    """Links between residents ``x`` and visitors ``y`` at one place, thinned to a spanning forest."""
    nodes = np.unique(np.concatenate([x, y]))
    label = np.arange(len(nodes))
    at_y, a, b = np.searchsorted(nodes, y), [], []
    for i in np.searchsorted(nodes, x):
        other = np.flatnonzero(label[at_y] != label[i])  # what is already joined needs no comparison
        hit = other[np.bitwise_count(y[other] ^ nodes[i]) <= distance]
        if len(hit):
            roots, first = np.unique(label[at_y[hit]], return_index=True)
            a += [nodes[i]] * len(roots)
            b += list(y[hit[first]])
            label[np.isin(label, roots)] = label[i]
    return np.array(a, dtype=np.uint64), np.array(b, dtype=np.uint64)


def _links(key: np.ndarray, fp: np.ndarray, home: np.ndarray, distance: int, most: int = 1 << 22):
    """Links within each place; the rows come in any order. Small places together in blocks, large ones one by one."""
    order = np.lexsort((~home, key))
    key, fp, home = key[order], fp[order], home[order]
    start = np.flatnonzero(np.r_[True, key[1:] != key[:-1]]) if len(key) else np.zeros(0, dtype=np.int64)
    size = np.diff(np.r_[start, len(key)])
    homes = np.add.reduceat(home.astype(np.int64), start) if len(start) else size
    live = (homes > 0) & (size > 1)
    big = live & (homes * size > 1 << 14)
    for s, n, h in zip(start[big], size[big], homes[big], strict=True):
        yield _forest(fp[s : s + h], fp[s : s + n], distance)
    s, n, h = (z[live & ~big] for z in (start, size, homes))
    work, at = np.cumsum(n * h), 0
    while at < len(s):
        end = max(at + 1, int(np.searchsorted(work, (work[at - 1] if at else 0) + most)))
        s_, n_, h_ = s[at:end], n[at:end], h[at:end]
        total = int((n_ * h_).sum())
        place = np.repeat(np.arange(len(s_)), n_ * h_)
        local = np.arange(total) - np.repeat(np.cumsum(n_ * h_) - n_ * h_, n_ * h_)
        x, y = fp[s_[place] + local // n_[place]], fp[s_[place] + local % n_[place]]
        hit = (x != y) & (np.bitwise_count(x ^ y) <= distance)
        yield x[hit], y[hit]
        at = end


def links(nodes: DataFrame, fp: str = "fp", distance: int = DISTANCE, segments: int = 3) -> DataFrame:
    """Links ``(a, b)`` that join all distinct fingerprints within ``distance`` bits as a transitive whole.

    Every pair within the distance is joined directly or through other links of the result.
    """
    spark = with_checkpoints(nodes.sparkSession)
    plan, n = AnchorPlan(distance, segments), partitions_of(spark)

    def send(batches):
        for b in (whole.slice(i, 1024) for whole in batches for i in range(0, len(whole), 1024)):
            key, own, home = plan.rows(b.column(0).to_numpy(zero_copy_only=False).view(np.uint64))
            yield pa.RecordBatch.from_arrays([pa.array(key.view(np.int64)), pa.array(own.view(np.int64)), pa.array(home)], ["anchor", "fp", "home"])
        release()

    placed = nodes.select(F.col(fp).alias("fp")).where("fp is not null").distinct().mapInArrow(send, "anchor long, fp long, home boolean")
    counts = placed.groupBy("anchor").agg(F.count("*").alias("n")).persist()
    try:
        total = counts.agg(F.sum("n")).first()[0] or 0
        limit = max(8192, total // 20_000)  # so at most 20,000 anchors are hot
        hot = counts.where(F.col("n") > limit).select("anchor", F.ceil(F.col("n") / limit).cast("int").alias("grid")).collect()
    finally:
        counts.unpersist()
    wide = spark.createDataFrame([(r["anchor"], r["grid"]) for r in hot], "anchor long, grid int")
    cell = F.pmod(F.xxhash64("fp"), F.col("grid")).cast("int")
    celled = (
        placed.join(F.broadcast(wide), "anchor", "left")
        .withColumn("grid", F.coalesce("grid", F.lit(1)))
        .withColumn("other", F.explode(F.expr("sequence(0, grid - 1)")))
        .select(
            F.xxhash64("anchor", F.when(F.col("home"), cell).otherwise(F.col("other")), F.when(F.col("home"), F.col("other")).otherwise(cell)).alias("place"),
            "fp", "home", "grid", "other", "anchor", cell.alias("cell"),
        )
    )
    # a resident is compared with residents too: in a cut anchor it also goes where visitors go
    guests = celled.where("grid > 1 and home").select(F.xxhash64("anchor", F.col("other"), F.col("cell")).alias("place"), "fp", F.lit(False).alias("home"))
    dealt = celled.select("place", "fp", "home").unionByName(guests).repartition(n, "place")

    def compare(batches):
        parts = [(b.column(0).to_numpy(zero_copy_only=False), b.column(1).to_numpy(zero_copy_only=False).view(np.uint64), b.column(2).to_numpy(zero_copy_only=False)) for b in batches]
        if parts:
            for a, b in _links(*(np.concatenate(c) for c in zip(*parts, strict=True)), distance):
                yield pa.RecordBatch.from_arrays([pa.array(a.view(np.int64)), pa.array(b.view(np.int64))], ["a", "b"])
        release()

    return dealt.mapInArrow(compare, "a long, b long").where("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()


def near_duplicates(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", shingle: int = SHINGLE, distance: int = DISTANCE, segments: int = 3) -> DataFrame:
    """``(doc_id, fingerprint, component_id)`` of every row of ``docs``.

    Null and empty texts have fingerprint zero and are linked like any other; rows that repeat stay rows; a row whose
    doc_id is null belongs to its class too but never names it. No rows give an empty table.
    """
    with_checkpoints(docs.sparkSession)
    own = fingerprints(docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).alias("text")), shingle=shingle).checkpoint()
    classes = own.groupBy("fp").agg(F.min("doc_id").alias("least"))
    joined = components(links(classes, "fp", distance, segments))
    rooted = classes.join(joined.withColumnRenamed("id", "fp"), "fp", "left").select("fp", "least", F.coalesce("component", "fp").alias("root"))
    named = rooted.join(rooted.groupBy("root").agg(F.min("least").alias("component_id")), "root").select("fp", "component_id")
    return own.join(named, "fp").select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def keep_one(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", most_ids: int = MOST_IDS, **options) -> DataFrame:
    """``docs`` with one row of every group of near copies: the one with the smallest id (of repeats, one).

    Rows without an id can't be named as anyone's copy and all stay. The ids that go are sent to all tasks if they are no
    more than ``most_ids``, and no text moves; beyond that they meet the rows in a shuffled join.
    """
    id_ = fresh("gone_id", docs.columns)
    near = near_duplicates(docs, doc_id, text, **options).where("doc_id is not null").checkpoint()
    gone = near.where("doc_id <> component_id").select(F.col("doc_id").alias(id_)).distinct()
    again = near.groupBy("doc_id").count().where("count > 1").join(gone, F.col("doc_id") == F.col(id_), "left_anti").select(F.col("doc_id").alias(id_))
    n_gone, n_again = gone.count(), again.count()
    hinted = F.broadcast if n_gone + n_again <= most_ids else lambda ids: ids
    own = F.col(doc_id) == F.col(id_)
    if not n_again:
        return docs.join(hinted(gone), own, "left_anti")
    single = docs.join(hinted(gone.unionByName(again)), own, "left_anti")
    return single.unionByName(docs.join(hinted(again), own, "left_semi").dropDuplicates([doc_id]))


def op1_simhash_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Fingerprint and near-copy component of every document."""
    return near_duplicates(read_table(spark, sf_dir, "documents"))
