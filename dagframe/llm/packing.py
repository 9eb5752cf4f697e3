"""Best-fit packing of token sequences after dominance reduction, on the histogram of lengths.

Packing needs only how many pieces have each length, and lengths are at most ``capacity``: the instance has a bounded
size however many documents there are. Reduction comes first: a set of pieces that provably is in some optimal packing is
fixed for good (Martello and Toth's dominance), for all equal pieces at once; what is left is packed best-fit by falling
length, bins of one content together. The plan is a table of intervals: the pieces of one length with ranks from..to go
to bins first.., so many in each, at an offset. Ranks come from counts by (length, salt), salts being many, so a length
that a third of all pieces have is ranked by many tasks.
"""

from __future__ import annotations

import zlib
from bisect import bisect_left, insort
from collections import Counter
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from dagframe.llm.common import partitions_of, read_table, release, with_checkpoints
from dagframe.llm.wordbpe import table_of, default_path

CAPACITY = 2048
SEPARATOR = (0).to_bytes(4, "little")


@dataclass
class Bins:
    """``count`` bins of equal content: runs of (length, how many)."""

    count: int
    runs: list[tuple[int, int]] = field(default_factory=list)

    def room(self, capacity: int) -> int:
        return capacity - sum(length * n for length, n in self.runs)


def _below(lengths: list[int], most: int) -> int | None:
    at = bisect_left(lengths, most + 1)
    return lengths[at - 1] if at else None


def _pair_sum(lengths: list[int], left: dict[int, int], most: int) -> int:
    """The largest sum up to ``most`` of two pieces that are left; 0 if no two fit."""
    best, low, high = 0, 0, len(lengths) - 1
    while low <= high:
        total = lengths[low] + lengths[high]
        if total > most:
            high -= 1
        elif low == high and left[lengths[low]] < 2:
            break
        else:
            best, low = max(best, total), low + 1
    return best


def _pair_above_all(lengths: list[int], left: dict[int, int], mate: int, room: int) -> int | None:
    """The longest piece beside ``mate`` in ``room``, if no two pieces that fit there are both longer than it."""
    own = [x for x in lengths if left[x] > (x == mate)]
    second = _below(own, room - mate)
    if second is None:
        return None
    longer = [x for x in lengths[bisect_left(lengths, second + 1) :][:2] for _ in range(min(2, left[x]))][:2]
    return second if len(longer) < 2 or sum(longer) > room else None


def _best_set(lengths: list[int], left: dict[int, int], room: int) -> list[int] | None:
    """The partners of a piece that dominate all others in ``room``: none, one or two; None if no such set is known.

    One partner dominates if it is as long as any sum that fits: two partners' sum is compared exactly; that three could sum
    to more than any two do is excluded only if the three shortest don't fit or the partner fills the room. Two partners
    dominate if no three fit and of any two that fit, one is no longer than the shorter and the other than the longer.
    """
    mate = _below(lengths, room)
    if mate is None:
        return []
    if mate == room:
        return [mate]
    shortest = [x for x in lengths[:3] for _ in range(min(3, left[x]))][:3]
    if len(shortest) == 3 and sum(shortest) <= room:
        return None
    if _pair_sum(lengths, left, room) <= mate:
        return [mate]
    second = _pair_above_all(lengths, left, mate, room)
    return None if second is None else [mate, second]


def reduced(left: dict[int, int], capacity: int) -> tuple[list[Bins], dict[int, int]]:
    """Bins of one, two or three pieces that dominate all others for their largest piece, and the pieces left over."""
    left, lengths, fixed = dict(left), sorted(left), []

    def change(length: int, by: int) -> None:
        now = left.get(length, 0) + by
        if now and not left.get(length):
            insort(lengths, length)
        elif not now and left.get(length):
            lengths.remove(length)
        left[length] = now

    for own in sorted(left, reverse=True):
        while left.get(own):
            change(own, -1)
            partners = _best_set(lengths, left, capacity - own)
            change(own, 1)
            if partners is None:
                break
            each = Counter([own, *partners])
            n = min(left[length] // k for length, k in each.items())
            fixed.append(Bins(n, sorted(each.items(), reverse=True)))
            for length, k in each.items():
                change(length, -n * k)
    return fixed, {k: n for k, n in left.items() if n}


def best_fit(left: dict[int, int], capacity: int) -> list[Bins]:
    """Best-fit by falling length, all pieces of a length and all bins of a content at a time."""
    full, by_room, rooms = [], {}, []

    def put(group: Bins) -> None:
        room = group.room(capacity)
        if room == 0:
            full.append(group)
            return
        if room not in by_room:
            by_room[room] = []
            insort(rooms, room)
        by_room[room].append(group)

    for own in sorted(left, reverse=True):
        n = left[own]
        while n:
            at = bisect_left(rooms, own)
            if at < len(rooms):
                room = rooms[at]
                group = by_room[room].pop()
                if not by_room[room]:
                    del by_room[room]
                    rooms.pop(at)
            else:
                room, group = capacity, Bins(n)
            each = min(room // own, n)
            used = min(group.count, n // each)
            if group.count > used and (room < capacity or group.runs):
                put(Bins(group.count - used, list(group.runs)))
            put(Bins(used, [*group.runs, (own, each)]))
            n -= used * each
    return full + [g for groups in by_room.values() for g in groups]


def packed(histogram: dict[int, int], capacity: int = CAPACITY) -> list[Bins]:
    """All bins for pieces given as {length: number}."""
    if bad := [k for k in histogram if not 0 < k <= capacity]:
        raise ValueError(f"lengths must be 1..{capacity}, not {bad[:3]}")
    fixed, left = reduced({k: n for k, n in histogram.items() if n}, capacity)
    return fixed + best_fit(left, capacity)


def intervals(bins: list[Bins]) -> list[tuple[int, int, int, int, int, int]]:
    """(length, first rank, past the last rank, first bin, pieces in each bin, offset of the first in its bin)."""
    out, ranks, number = [], {}, 0
    for group in bins:
        offset = 0
        for length, each in group.runs:
            low = ranks.get(length, 0)
            ranks[length] = low + each * group.count
            out.append((length, low, ranks[length], number, each, offset))
            offset += length * each
        number += group.count
    return out


def pieces(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", path: str | None = None, capacity: int = CAPACITY) -> DataFrame:
    """``(doc_id, piece, start, length, ids_crc32)``: every text's ids and a closing 0, cut every ``capacity`` ids."""
    path, step = path or default_path(), 4 * capacity

    def run(batches):
        table = table_of(path, False)
        for b in batches:
            ids = b.column(0).to_pylist()
            rows: list[list] = [[], [], [], [], []]
            for own, data in zip(ids, table.of(b.column(1).cast(pa.binary()).to_pylist()), strict=True):
                data += SEPARATOR
                for k, at in enumerate(range(0, len(data), step)):
                    part = data[at : at + step]
                    for column, value in zip(rows, (own, k, at // 4, len(part) // 4, zlib.crc32(part)), strict=True):
                        column.append(value)
            yield pa.RecordBatch.from_arrays([pa.array(rows[0], b.schema.field(0).type), pa.array(rows[1], pa.int32()), *(pa.array(r, pa.int64()) for r in rows[2:])], ["doc_id", "piece", "start", "length", "ids_crc32"])
        release()

    kind = docs.schema[doc_id].dataType.simpleString()
    slim = docs.select(F.col(doc_id).alias("doc_id"), F.coalesce(F.col(text), F.lit("")).alias("t"))
    return slim.mapInArrow(run, f"doc_id {kind}, piece int, start long, length long, ids_crc32 long")


def assign(cut: DataFrame, capacity: int = CAPACITY) -> DataFrame:
    """``cut``, which needs a ``length``, with ``sequence_id`` and ``offset``. It is read more than once: cut its lineage."""
    spark = cut.sparkSession
    salts = max(64, 4 * partitions_of(spark))
    salted = cut.withColumn("salt_", F.pmod(F.xxhash64(*[c for c in ("doc_id", "piece") if c in cut.columns] or [F.monotonically_increasing_id()]), F.lit(salts)).cast("int"))
    counts = salted.groupBy("length", "salt_").agg(F.count("*").alias("n_"))
    histogram = {r["length"]: r["n_"] for r in counts.groupBy("length").agg(F.sum("n_").alias("n_")).collect()}  # at most `capacity` rows
    plan = spark.createDataFrame(intervals(packed(histogram, capacity)), "length long, low_ long, high_ long, bin_ long, each_ long, at_ long")
    before = counts.withColumn("before_", F.sum("n_").over(Window.partitionBy("length").orderBy("salt_")) - F.col("n_")).drop("n_")
    order = [F.col(c) for c in ("doc_id", "piece") if c in cut.columns] or [F.lit(0)]
    ranked = salted.withColumn("nth_", F.row_number().over(Window.partitionBy("length", "salt_").orderBy(*order)) - 1)
    placed = ranked.join(before, ["length", "salt_"]).withColumn("rank_", F.col("nth_") + F.col("before_"))
    own = placed.join(F.broadcast(plan.withColumnRenamed("length", "own_")), (F.col("length") == F.col("own_")) & (F.col("rank_") >= F.col("low_")) & (F.col("rank_") < F.col("high_")))
    return own.select(
        *cut.columns,
        (F.col("bin_") + F.floor((F.col("rank_") - F.col("low_")) / F.col("each_"))).cast("long").alias("sequence_id"),
        (F.col("at_") + F.pmod(F.col("rank_") - F.col("low_"), F.col("each_")) * F.col("length")).cast("long").alias("offset"),
    )


def pack(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", path: str | None = None, capacity: int = CAPACITY) -> DataFrame:
    """One row per piece of every document with its sequence and its place there.

    Null and empty texts are the closing 0 alone; rows that repeat are packed each; no documents give no rows.
    """
    with_checkpoints(docs.sparkSession)
    return assign(pieces(docs, doc_id, text, path, capacity).checkpoint(), capacity)


def op8_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents in sequences of at most 2048 tokens."""
    return pack(read_table(spark, sf_dir, "documents"))
