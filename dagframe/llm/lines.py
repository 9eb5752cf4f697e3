"""Line dedup that can be undone: sharded cuckoo filters before exact reference counts.

The exact table holds one posting (key, doc_id) for each document and line key; its counts say in how many documents a key
is and which the last one is. A key is *crowded* at ``min_docs`` documents. Crowded keys of a shard sit in that shard's
cuckoo filter, which a scan asks first: only lines that a filter lets through meet the exact table, so a false positive
costs a lookup and never a line. New documents add postings, removed documents take theirs away, and the filters take in
or give up the keys that cross the threshold; what a deletion leaves is what an index without the document would be.

A scan always asks the filters. What they let through meets the crowded keys beside the scan if these are few, else in a
join; shards grow in number with the keys, so that one shard's filter is built in one task's memory.

Null and empty texts are one empty line. Rows without an id hold no postings and keep all lines; rows that repeat an id
are one document for the counts, and each keeps its own row.
"""

from __future__ import annotations

from functools import reduce
from hashlib import md5

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from dagframe.llm.common import read_table, release, with_checkpoints
from dagframe.llm.cuckoo import CuckooFilter, ShardedFilters

MIN_CHARS = 40
MIN_DOCS = 5
SHARDS = 64
SHARD_KEYS = 1 << 16
BROADCAST_BYTES = 32 << 20
FILTER_BYTES = 256 << 20
KEY_BYTES = 16


def shard_of(key: Column, shards: int = SHARDS) -> Column:
    """The key's last four bytes modulo the number of shards."""
    return F.pmod(F.conv(F.hex(F.substring(key, 13, 4)), 16, 10).cast("long"), F.lit(shards)).cast("int")


def line_key(line: bytes, min_chars: int = MIN_CHARS) -> bytes | None:
    """The 16-byte digest of a line's key: trimmed and lower-cased within ASCII; None for a key that is too short."""
    key = line.strip().lower()
    if len(key) < min_chars or (not key.isascii() and len(key.decode("utf-8", "surrogatepass")) < min_chars):
        return None
    return md5(key, usedforsecurity=False).digest()


def postings(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", min_chars: int = MIN_CHARS, distinct: bool = True) -> DataFrame:
    """``(key, doc_id)``, each once (for each row of ``docs``, if not ``distinct``), of all lines whose key has at least ``min_chars`` code points."""

    def run(batches):
        for b in batches:
            keys, at = [], []
            for i, t in enumerate(b.column(1).cast(pa.binary()).to_pylist()):
                own = {line_key(x, min_chars) for x in t.split(b"\n")} - {None}
                keys += own
                at += [i] * len(own)
            yield pa.RecordBatch.from_arrays([pa.array(keys, pa.binary()), b.column(0).take(pa.array(at, pa.int64()))], ["key", "doc_id"])
        release()

    kind = docs.schema[doc_id].dataType.simpleString()
    each = docs.where(F.col(doc_id).isNotNull() & F.col(text).isNotNull()).select(F.col(doc_id).alias("doc_id"), F.col(text).alias("t"))
    found = each.mapInArrow(run, f"key binary, doc_id {kind}")
    return found.distinct() if distinct else found


def reference_counts(posted: DataFrame) -> DataFrame:
    """The exact table ``(key, n_docs, last_doc)``."""
    return posted.groupBy("key").agg(F.count("*").alias("n_docs"), F.max("doc_id").alias("last_doc"))


def filters(crowded: DataFrame, shards: int = SHARDS) -> DataFrame:
    """``(shard, filter)``: the shards' cuckoo filters over the keys of ``crowded``."""

    def build(table: pa.Table) -> pa.Table:
        return pa.table({"shard": pa.array([table["shard"][0].as_py()], pa.int32()), "filter": pa.array([CuckooFilter.of(table["key"].to_pylist()).dump()], pa.binary())})

    return crowded.select(shard_of(F.col("key"), shards).alias("shard"), "key").groupBy("shard").applyInArrow(build, "shard int, filter binary")


def updated_filters(old: DataFrame, gained: DataFrame, lost: DataFrame, crowded: DataFrame, shards: int = SHARDS) -> DataFrame:
    """``old`` with the keys of ``gained`` put in and those of ``lost`` taken out; a shard that is full is built anew."""
    moves = gained.select("key", F.lit(True).alias("gain")).unionByName(lost.select("key", F.lit(False).alias("gain")))
    rows = (
        moves.select(shard_of(F.col("key"), shards).alias("shard"), "key", F.col("gain").cast("int").alias("what"), F.lit(None).cast("binary").alias("filter"))
        .unionByName(crowded.select(shard_of(F.col("key"), shards).alias("shard"), "key", F.lit(2).alias("what"), F.lit(None).cast("binary").alias("filter")))
        .unionByName(old.select("shard", F.lit(None).cast("binary").alias("key"), F.lit(3).alias("what"), "filter"))
    )

    def change(frame: pd.DataFrame) -> pd.DataFrame:
        part = lambda what: list(frame.loc[frame["what"] == what, "key"])
        now = frame.loc[frame["what"] == 3, "filter"]
        if len(now):
            held = CuckooFilter.load(now.iloc[0])
            for key in part(0):
                held.delete(key)
            if not all(held.insert(key) for key in part(1)):
                held = CuckooFilter.of(part(2))
        else:
            held = CuckooFilter.of(part(2))
        return pd.DataFrame({"shard": [int(frame["shard"].iloc[0])], "filter": [held.dump()]})

    return rows.groupBy("shard").applyInPandas(change, "shard int, filter binary")


class LineIndex:
    """Exact postings and the filters over their crowded keys, open to insertions and deletions."""

    def __init__(self, posted: DataFrame, min_docs: int = MIN_DOCS, min_chars: int = MIN_CHARS, sharded: DataFrame | None = None, shards: int = SHARDS):
        self.postings, self.min_docs, self.min_chars, self.shards = posted, min_docs, min_chars, shards
        self.crowded = reference_counts(posted).where(F.col("n_docs") >= min_docs)
        self.filters = filters(self.crowded, shards) if sharded is None else sharded

    @classmethod
    def of(cls, docs: DataFrame, doc_id: str = "doc_id", text: str = "text", min_docs: int = MIN_DOCS, min_chars: int = MIN_CHARS) -> LineIndex:
        with_checkpoints(docs.sparkSession)
        made = cls.__new__(cls)
        made.postings, made.min_docs, made.min_chars = postings(docs, doc_id, text, min_chars), min_docs, min_chars
        made.crowded = reference_counts(made.postings).where(F.col("n_docs") >= min_docs).checkpoint()
        made.shards = max(SHARDS, -(-made.crowded.count() // SHARD_KEYS))
        made.filters = filters(made.crowded, made.shards).checkpoint()
        return made

    def _moved(self, posted: DataFrame) -> LineIndex:
        new = reference_counts(posted).where(F.col("n_docs") >= self.min_docs)
        gained, lost = new.join(self.crowded, "key", "left_anti"), self.crowded.join(new, "key", "left_anti")
        return LineIndex(posted, self.min_docs, self.min_chars, updated_filters(self.filters, gained, lost, new, self.shards), self.shards)

    def insert(self, docs: DataFrame, doc_id: str = "doc_id", text: str = "text") -> LineIndex:
        """The index with these documents too; ids that it has already get the union of their lines."""
        return self._moved(self.postings.unionByName(postings(docs, doc_id, text, self.min_chars)).distinct())

    def delete(self, ids: DataFrame, doc_id: str = "doc_id") -> LineIndex:
        """The index without the documents whose ids ``ids`` lists."""
        return self._moved(self.postings.join(ids.select(F.col(doc_id).alias("doc_id")), "doc_id", "left_anti"))

    def apply(self, docs: DataFrame, doc_id: str = "doc_id", text: str = "text", most_bytes: int = BROADCAST_BYTES, most_filter_bytes: int = FILTER_BYTES) -> DataFrame:
        """All columns of ``docs`` in a struct ``row``, with ``n_lines``, ``n_dropped`` and ``kept``, the text that stays.

        The filters go to all tasks. If crowded keys and filters take no more than ``most_bytes`` together, the keys go there too
        and no text moves. Beyond that the lines that a filter lets through meet the crowded keys in a join, and texts meet what they
        lose. Filters beyond ``most_filter_bytes`` (some 100 million crowded keys) go out in parts, each asked by the lines of its shards.
        """
        sizes = self.filters.agg(F.sum(F.length("filter"))).first()[0] or 0
        beside = self.crowded.count() * (KEY_BYTES + 8) + sizes <= most_bytes
        return self._beside(docs, doc_id, text) if beside else self._joined(docs, doc_id, text, max(1, -(-sizes // most_filter_bytes)))

    def _table(self) -> tuple[np.ndarray, pa.Array]:
        """Crowded keys in rising order, with their last documents; 24 bytes each for ids that are numbers."""
        found = self.crowded.select("key", "last_doc").toArrow().sort_by("key")
        return np.array(found["key"].to_pylist(), dtype=f"S{KEY_BYTES}"), found["last_doc"].combine_chunks()

    def _sent(self, part: int = 0, parts: int = 1):
        """Every ``parts``-th shard's filter, sent to all tasks."""
        rows = self.filters.where(F.col("shard") % parts == part).toLocalIterator()
        return self.filters.sparkSession.sparkContext.broadcast({r["shard"]: bytes(r["filter"]) for r in rows})

    def _beside(self, docs: DataFrame, doc_id: str, text: str) -> DataFrame:
        held = self._sent()
        names, shards = [f"k{i}" for i in range(len(docs.columns))], self.shards
        exact = docs.sparkSession.sparkContext.broadcast(self._table())
        own, body, min_chars = docs.columns.index(doc_id), docs.columns.index(text), self.min_chars
        asked_: list[ShardedFilters] = []

        def run(batches):
            if not asked_:
                asked_.append(ShardedFilters(held.value, shards))
            known, last_ = exact.value
            for b in batches:
                split = [(t or b"").split(b"\n") for t in b.column(body).cast(pa.binary()).to_pylist()]
                keys = [[line_key(x, min_chars) for x in lines] for lines in split]
                asked = list({k for ks in keys for k in ks if k is not None})
                near = [k for k, hit in zip(asked, asked_[0].contains(asked).tolist(), strict=True) if hit] if len(known) else []
                at = np.minimum(np.searchsorted(known, np.array(near, dtype=known.dtype)), len(known) - 1) if near else np.zeros(0, dtype=np.int64)
                true = np.flatnonzero(known[at] == np.array(near, dtype=known.dtype)) if near else at
                last = dict(zip([near[i] for i in true], last_.take(pa.array(at[true])).to_pylist(), strict=True))
                kept, n_dropped = [], []
                for i, lines, ks in zip(b.column(own).to_pylist(), split, keys, strict=True):
                    stays = lines if i is None else [x for x, k in zip(lines, ks, strict=True) if last.get(k, i) == i]
                    kept.append(b"\n".join(stays))
                    n_dropped.append(len(lines) - len(stays))
                more = [pa.array([len(x) for x in split], pa.int64()), pa.array(n_dropped, pa.int64()), pa.array(kept, pa.binary()).cast(pa.string())]
                yield pa.RecordBatch.from_arrays([*b.columns, *more], [*names, "n_lines", "n_dropped", "kept"])
            release()

        renamed = docs.select(*[F.col(f"`{c}`").alias(n) for c, n in zip(docs.columns, names, strict=True)])
        kinds = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in renamed.schema.fields)
        done = renamed.mapInArrow(run, f"{kinds}, n_lines long, n_dropped long, kept string")
        return done.select(F.struct(*[F.col(n).alias(c) for c, n in zip(docs.columns, names, strict=True)]).alias("row"), "n_lines", "n_dropped", "kept")

    def _passed(self, posted: DataFrame, part: int, parts: int) -> DataFrame:
        """The postings of every ``parts``-th shard that their filters let through."""
        shards, held = self.shards, self._sent(part, parts)
        asked_: list[ShardedFilters] = []

        def run(batches):
            if not asked_:
                asked_.append(ShardedFilters(held.value, shards))
            for b in batches:
                yield b.filter(pa.array(asked_[0].contains(b.column(0).to_pylist()), pa.bool_()))
            release()

        return posted.mapInArrow(run, posted.schema)

    def _joined(self, docs: DataFrame, doc_id: str, text: str, parts: int) -> DataFrame:
        posted = postings(docs, doc_id, text, self.min_chars, False)
        near = reduce(DataFrame.unionByName, [self._passed(posted, k, parts) for k in range(parts)]).distinct()
        lost = near.join(self.crowded.select("key", "last_doc"), "key").where("doc_id <> last_doc").groupBy("doc_id").agg(F.collect_set("key").alias("keys"))
        names = [f"k{i}" for i in range(len(docs.columns))]
        rows = docs.select(*[F.col(f"`{c}`").alias(n) for c, n in zip(docs.columns, names, strict=True)])
        joined = rows.join(lost, F.col(names[docs.columns.index(doc_id)]) == F.col("doc_id"), "left").drop("doc_id")
        body, min_chars = docs.columns.index(text), self.min_chars

        def run(batches):
            for b in batches:
                split = [(t or b"").split(b"\n") for t in b.column(body).cast(pa.binary()).to_pylist()]
                kept = []
                for lines, keys in zip(split, b.column(len(names)).to_pylist(), strict=True):
                    gone = set(keys or ())
                    kept.append([x for x in lines if line_key(x, min_chars) not in gone] if gone else lines)
                more = [pa.array([len(x) for x in split], pa.int64()), pa.array([len(x) - len(y) for x, y in zip(split, kept, strict=True)], pa.int64()), pa.array([b"\n".join(x) for x in kept], pa.binary()).cast(pa.string())]
                yield pa.RecordBatch.from_arrays([*b.columns[:-1], *more], [*names, "n_lines", "n_dropped", "kept"])
            release()

        kinds = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.schema.fields)
        done = joined.mapInArrow(run, f"{kinds}, n_lines long, n_dropped long, kept string")
        return done.select(F.struct(*[F.col(n).alias(c) for c, n in zip(docs.columns, names, strict=True)]).alias("row"), "n_lines", "n_dropped", "kept")


def op10_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Lines before and after, and the digest of what stays, of every document."""
    docs = read_table(spark, sf_dir, "documents").select("doc_id", "text")
    return LineIndex.of(docs).apply(docs).select("row.doc_id", "n_lines", "n_dropped", F.sha2("kept", 256).alias("kept_sha256"))


_SQL_KEY = "translate(trim(line, ' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"

OP10_SQL = f"""
WITH split AS (
  SELECT doc_id, string_split(coalesce(text, ''), chr(10)) AS lines FROM documents
), each AS (
  SELECT doc_id, unnest(lines) AS line, generate_subscripts(lines, 1) AS nr FROM split
), keyed AS (
  SELECT doc_id, nr, line, {_SQL_KEY} AS key FROM each
), crowded AS (
  SELECT key, max(doc_id) AS last_doc FROM keyed WHERE length(key) >= {MIN_CHARS} GROUP BY key HAVING count(DISTINCT doc_id) >= {MIN_DOCS}
), marked AS (
  SELECT k.doc_id, k.nr, k.line, c.last_doc IS NOT NULL AND c.last_doc <> k.doc_id AS gone FROM keyed k LEFT JOIN crowded c ON k.key = c.key
)
SELECT doc_id, count(*)::BIGINT AS n_lines, (count(*) FILTER (gone))::BIGINT AS n_dropped,
  sha256(coalesce(string_agg(line, chr(10) ORDER BY nr) FILTER (NOT gone), '')) AS kept_sha256
FROM marked GROUP BY doc_id
"""
