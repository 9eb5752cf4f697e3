"""Ids and token counts of whole texts under a word-level BPE vocabulary of the tokenizers library.

Such a vocabulary never lets a token reach over white space, so a text's ids are those of its white-space chunks in
order. Each Python worker therefore keeps a table from chunk to ids (or to their number) and asks the library for the
chunks that it lacks, many at once. Chunks are lower-cased first (A-Z, which the vocabulary's normaliser does anyway) and
split at ASCII white space only. A text that holds ``<|`` could hold a special token, whose place the library decides: such
a text goes to the library whole.

The table is arrays: 64-bit polynomial hashes of chunks in rising order, the chunks' bytes, and what they stand for. The
chunks of some megabytes of text are cut, hashed, looked up and laid out by array operations, without an object per chunk.
A hash only proposes: bytes are compared, and texts in which two chunks share a hash go to the library whole.
"""

from __future__ import annotations

from array import array
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from dagframe.llm.common import read_table, release, same_spans

SLICE = 1 << 19
KNOWN = 600_000
ROW = 2048
FREQUENT = 65_536
SAMPLE = 10_000
VOCABULARY = "word_bpe_49k.json"

_FACTOR = 0x9E3779B97F4A7C15 * 2 + 1 & (1 << 64) - 1
_SPACES = np.zeros(256, dtype=bool)
_SPACES[[9, 10, 11, 12, 13, 32]] = True

_libraries: dict = {}
_tables: dict = {}
_powers: list[np.ndarray] = []


def default_path() -> str:
    import public_tokenizers

    return public_tokenizers.path(VOCABULARY)


def library(path: str):
    """The library's tokenizer, once per process, without truncation and padding."""
    if path not in _libraries:
        import os

        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        made = Tokenizer.from_file(path)
        made.no_truncation()
        made.no_padding()
        _libraries[path] = made
    return _libraries[path]


def slices(text: bytes, size: int = SLICE) -> Iterator[bytes]:
    """``text`` in slices of about ``size`` bytes that end at ASCII white space, so that no chunk is cut."""
    at = 0
    while len(text) - at > size:
        end = min((p for p in (text.find(c, at + size) for c in (b" ", b"\n", b"\t", b"\r")) if p >= 0), default=len(text))
        yield text[at:end]
        at = end
    yield text[at:]


def _power(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers 0..n-1 of the hash's factor and of its inverse, modulo 2**64."""
    if not _powers or len(_powers[0]) < n:
        size = max(n, SLICE + (1 << 16))
        _powers[:] = [np.cumprod(np.r_[np.uint64(1), np.full(size - 1, np.uint64(f), dtype=np.uint64)], dtype=np.uint64) for f in (_FACTOR, pow(_FACTOR, -1, 1 << 64))]
    return _powers[0][:n], _powers[1][:n]


def chunk_places(data: bytes) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(first bytes, past the last bytes, hashes) of the white-space chunks of lower-cased ``data``."""
    raw = np.frombuffer(data, dtype=np.uint8)
    gap = np.ones(len(raw) + 2, dtype=bool)
    gap[1:-1] = _SPACES[raw]
    edge = np.flatnonzero(gap[1:] != gap[:-1])
    start, end = edge[::2], edge[1::2]
    up, down = _power(len(raw) + 1)
    sums = np.zeros(len(raw) + 1, dtype=np.uint64)
    np.cumsum((raw.astype(np.uint64) + np.uint64(1)) * up[:-1], out=sums[1:])
    return start, end, (sums[end] - sums[start]) * down[start]


def _appended(pool: np.ndarray, used: int, new: np.ndarray) -> tuple[np.ndarray, int]:
    """``pool`` with ``new`` after its first ``used`` places, and how many are used then; it grows by doubling."""
    if used + len(new) > len(pool):
        pool = np.concatenate([pool[:used], np.zeros(used + 2 * len(new), dtype=pool.dtype)])
    pool[used : used + len(new)] = new
    return pool, used + len(new)


class ChunkTable:
    """From chunk to ids or, with ``counts``, to their number."""

    def __init__(self, path: str, counts: bool, first: tuple[list[bytes], np.ndarray] | None = None, most: int = KNOWN):
        """``first``: chunks and their numbers of ids, of which a table of counts is never without."""
        self.library, self.counts, self.most, self.groups = library(path), counts, most, 0
        words = self.library.get_vocab()
        self.closing = np.zeros(1 + max(words.values()), dtype=bool)
        self.closing[[i for token, i in words.items() if token.endswith("</w>")]] = True
        self.first = None
        self._begin()
        if first and counts:
            self._add(*first)
            self.first = {k: v.copy() for k, v in self._columns().items()}, self.used, self.text_used

    def _columns(self) -> dict[str, np.ndarray]:
        return {k: getattr(self, k) for k in ("hashes", "sizes", "at", "text_at", "text_size", "pool", "text")}

    def _begin(self) -> None:
        none = np.zeros(0, dtype=np.int64)
        self.hashes, self.sizes, self.at, self.text_at, self.text_size = none.astype(np.uint64), none.astype(np.int32), none, none, none
        self.pool, self.used, self.text, self.text_used = np.zeros(1 << 16, dtype=np.uint32), 0, np.zeros(1 << 16, dtype=np.uint8), 0
        if self.first:
            self.__dict__ |= {k: v.copy() for k, v in self.first[0].items()}
            self.used, self.text_used = self.first[1:]

    def _add(self, chunks: list[bytes], sizes: np.ndarray) -> None:
        """Take in chunks and their sizes; of two with one hash the first only."""
        data = b"\n".join(chunks)
        _, _, hashes = chunk_places(data)
        if len(hashes) == len(chunks):
            own, first = np.unique(hashes, return_index=True)
            self._learn(own, [chunks[i] for i in first], sizes[first])

    def ask(self, chunks: list[bytes]) -> list[bytes]:
        """Each chunk's ids as little-endian unsigned 32-bit integers.

        Chunks of letters alone are asked for many in a row and told apart by their last tokens. A comma or full stop after
        letters is a token of its own.
        """
        texts, out = [c.decode() for c in chunks], [b""] * len(chunks)
        marks = {m: array("I", self.library.encode(m, add_special_tokens=False).ids).tobytes() for m in ",."}
        cores = [t[:-1] if t[-1] in marks and t[:-1].isalpha() else t for t in texts]
        plain, rest = [i for i, t in enumerate(cores) if t.isalpha()], [i for i, t in enumerate(cores) if not t.isalpha()]
        for at in range(0, len(plain), ROW):
            row = plain[at : at + ROW]
            ids = np.array(self.library.encode(" ".join([cores[i] for i in row]), add_special_tokens=False).ids, dtype="<u4")
            ends = (4 * np.flatnonzero(self.closing[ids]) + 4).tolist()
            if len(ends) != len(row):  # a letter whose lower case is more than letters
                rest += row
                continue
            data, start = ids.tobytes(), 0
            for i, end in zip(row, ends, strict=True):
                out[i] = data[start:end] if cores[i] is texts[i] else data[start:end] + marks[texts[i][-1]]
                start = end
        for at in range(0, len(rest), ROW):
            row = rest[at : at + ROW]
            for i, e in zip(row, self.library.encode_batch_fast([texts[i] for i in row], add_special_tokens=False), strict=True):
                out[i] = array("I", e.ids).tobytes()
        return out

    def _learn(self, hashes: np.ndarray, chunks: list[bytes], sizes: np.ndarray | None = None) -> None:
        values = self.ask(chunks) if sizes is None else []
        sizes = np.array([len(v) for v in values], dtype=np.int32) // 4 if sizes is None else sizes
        at = self.used + np.cumsum(sizes, dtype=np.int64) - sizes
        if not self.counts:
            self.pool, self.used = _appended(self.pool, self.used, np.frombuffer(b"".join(values), dtype="<u4"))
        text_size = np.array([len(c) for c in chunks], dtype=np.int64)
        text_at = self.text_used + np.cumsum(text_size) - text_size
        self.text, self.text_used = _appended(self.text, self.text_used, np.frombuffer(b"".join(chunks), dtype=np.uint8))
        every = np.concatenate([self.hashes, hashes])
        order = np.argsort(every, kind="stable")
        merged = lambda old, new: np.concatenate([old, new])[order]
        self.hashes, self.sizes, self.at = every[order], merged(self.sizes, sizes), merged(self.at, at)
        self.text_at, self.text_size = merged(self.text_at, text_at), merged(self.text_size, text_size)

    def _found(self, hashes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        at = np.minimum(np.searchsorted(self.hashes, hashes), max(0, len(self.hashes) - 1))
        return at, self.hashes[at] == hashes if len(self.hashes) else np.zeros(len(hashes), dtype=bool)

    def _by_library(self, parts: list[bytes]) -> list:
        ids = [self.library.encode(p.decode(), add_special_tokens=False).ids for p in parts]
        return [len(x) if self.counts else array("I", x).tobytes() for x in ids]

    def _group(self, parts: list[bytes]) -> list:
        """Values of texts that together have some megabytes."""
        data = b"\n".join(parts).lower()
        start, end, hashes = chunk_places(data)
        raw = np.frombuffer(data, dtype=np.uint8)
        codes, distinct = pd.factorize(hashes)
        first = np.empty(len(distinct), dtype=np.int64)
        first[codes[::-1]] = np.arange(len(codes) - 1, -1, -1)
        size = end - start
        if len(codes) and not ((size == size[first][codes]).all() and same_spans(raw, start, raw, start[first][codes], size).all()):
            return self._by_library(parts)
        order = np.argsort(distinct)
        asked, places = distinct[order], first[order]
        at, known = self._found(asked)
        if not known.all():
            if len(self.hashes) + int((~known).sum()) > self.most:  # the table begins anew
                self._begin()
                at, known = self._found(asked)
            new = places[~known]
            self._learn(asked[~known], [data[s:e] for s, e in zip(start[new].tolist(), end[new].tolist(), strict=True)])
            at, known = self._found(asked)
        if len(at) and not ((self.text_size[at] == size[places]).all() and same_spans(raw, start[places], self.text, self.text_at[at], size[places]).all()):
            return self._by_library(parts)
        own = np.empty(len(distinct), dtype=np.int64)
        own[order] = at
        which = own[codes]
        sizes = self.sizes[which].astype(np.int64)
        past = np.r_[0, np.cumsum(sizes)]
        border = np.searchsorted(start, np.cumsum([0] + [len(p) + 1 for p in parts]))
        cut = past[border].tolist()
        if self.counts:
            return [b - a for a, b in zip(cut, cut[1:], strict=False)]
        flat = self.pool[np.repeat(self.at[which] - past[:-1], sizes) + np.arange(past[-1])].tobytes()
        return [flat[4 * a : 4 * b] for a, b in zip(cut, cut[1:], strict=False)]

    def of(self, texts: list[bytes]) -> list:
        """Ids (bytes) or counts of texts, in order."""
        out: list = [0 if self.counts else b""] * len(texts)
        parts: list[bytes] = []
        owners: list[int] = []
        size = 0

        def flush() -> None:
            self.groups += 1
            if self.groups % 32 == 0:
                release()
            for i, value in zip(owners, self._group(parts), strict=True):
                out[i] += value
            parts.clear()
            owners.clear()

        for i, text in enumerate(texts):
            if b"<|" in text:
                out[i] = self._by_library([text])[0]
                continue
            for part in slices(text):
                parts.append(part)
                owners.append(i)
                size += len(part)
                if size > SLICE:
                    flush()
                    size = 0
        if parts:
            flush()
        return out


def table_of(path: str, counts: bool, first: tuple[list[bytes], np.ndarray] | None = None) -> ChunkTable:
    """This worker's table, kept between tasks."""
    key = (path, counts, None if first is None else hash(tuple(first[0])))
    if key not in _tables:
        _tables.clear()
        _tables[key] = ChunkTable(path, counts, first)
    return _tables[key]


def frequent_chunks(docs: DataFrame, text: str = "text", most: int = FREQUENT, sample: int = SAMPLE) -> list[bytes]:
    """At most ``most`` of the most frequent chunks of about ``sample`` rows drawn at random; chunks of over 64 bytes are left out.

    One task reads the drawn rows, whose number is bounded, and keeps a bounded summary (rare chunks go when it is full), so no
    chunk is shuffled. Which chunks come out changes speed, never a result: counts themselves cover every row.
    """

    def summary(batches):
        seen: Counter = Counter()
        for b in batches:
            for part in (p for x in b.column(0).cast(pa.binary()).to_pylist() for p in slices(x)):
                seen.update(w for w in part.lower().split() if len(w) <= 64)
                if len(seen) > 8 * most:
                    seen = Counter(dict(seen.most_common(2 * most)))
        top = [w for w, n in sorted(seen.most_common(most), key=lambda x: (-x[1], x[0])) if b"<|" not in w]
        yield pa.RecordBatch.from_arrays([pa.array(top, pa.binary())], ["chunk"])
        release()

    n = docs.count()
    texts = docs.select(F.coalesce(F.col(text), F.lit("")).alias("t"))
    drawn = texts.sample(min(1.0, sample / n), 7) if n > sample else texts
    return [bytes(r["chunk"]) for r in drawn.repartition(1).mapInArrow(summary, "chunk binary").collect()]


def token_counts(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", path: str | None = None, frequent: int = FREQUENT, limit: int = 2048, sample: int = SAMPLE) -> DataFrame:
    """``(doc_id, n_bytes, n_tokens, over_limit)`` of every row; null texts count as empty, repeated rows each.

    Two tiers, both on the scan's side: a broadcast table with the lengths of at most ``frequent`` chunks of at most 64 bytes each,
    and what each worker adds to it for the rest. No chunk is shuffled.
    """
    path = path or default_path()
    top = frequent_chunks(docs, text, frequent, sample)
    sizes = np.array([len(v) // 4 for v in ChunkTable(path, True).ask(top)], dtype=np.int32)
    first = docs.sparkSession.sparkContext.broadcast((top, sizes))

    def run(batches):
        table = table_of(path, True, first.value)
        for b in batches:
            texts = b.column(1).cast(pa.binary()).to_pylist()
            n = pa.array(table.of(texts), pa.int64())
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([len(x) for x in texts], pa.int64()), n], ["doc_id", "n_bytes", "n_tokens"])
        release()

    kind = docs.schema[doc_id].dataType.simpleString()
    slim = docs.select(F.col(doc_id).alias("doc_id"), F.coalesce(F.col(text), F.lit("")).alias("t"))
    return slim.mapInArrow(run, f"doc_id {kind}, n_bytes long, n_tokens long").withColumn("over_limit", F.col("n_tokens") > limit)


def op5_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bytes and tokens of every document."""
    return token_counts(read_table(spark, sf_dir, "documents"))
