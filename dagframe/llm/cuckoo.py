"""A cuckoo filter over 128-bit keys: 16-bit fingerprints, four to a bucket, with insertion and deletion."""

from __future__ import annotations

import numpy as np

SLOTS = 4
KICKS = 400


class CuckooFilter:
    """Membership with rare false positives and no false negatives; keys may be taken out again.

    ``keys`` are 16-byte digests: their first eight bytes choose the bucket, the next two are the fingerprint. A key may be
    in once only; who inserts keeps the exact table that says so, from which a full filter is built anew twice as large.
    """

    def __init__(self, buckets: int = 16):
        self.table = np.zeros((max(2, 1 << (buckets - 1).bit_length()), SLOTS), dtype=np.uint16)

    @classmethod
    def of(cls, keys: list[bytes]) -> CuckooFilter:
        made = cls(max(16, int(len(keys) / SLOTS / 0.85) + 1))
        while not all(made.insert(k) for k in keys):
            made = cls(2 * len(made.table))
        return made

    @classmethod
    def load(cls, data: bytes) -> CuckooFilter:
        made = cls(2)
        made.table = np.frombuffer(data, dtype=np.uint16).reshape(-1, SLOTS).copy()
        return made

    def dump(self) -> bytes:
        return self.table.tobytes()

    def places(self, keys: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        mark, low = marks(np.frombuffer(b"".join(k[:10] for k in keys), dtype=np.uint8).reshape(-1, 10))
        one = low & np.uint64(len(self.table) - 1)
        return mark, one, self._other(one, mark)

    def _other(self, bucket, mark):
        return (bucket ^ step_of(mark)) & np.uint64(len(self.table) - 1)

    def insert(self, key: bytes) -> bool:
        """False if there is no room."""
        mark, one, two = (int(x[0]) for x in self.places([key]))
        for bucket in (one, two):
            if len(free := np.flatnonzero(self.table[bucket] == 0)):
                self.table[bucket, free[0]] = mark
                return True
        bucket = two
        for kick in range(KICKS):
            slot = (kick * 7 + mark) % SLOTS
            mark, self.table[bucket, slot] = int(self.table[bucket, slot]), mark
            bucket = int(self._other(np.uint64(bucket), np.uint16(mark)))
            if len(free := np.flatnonzero(self.table[bucket] == 0)):
                self.table[bucket, free[0]] = mark
                return True
        return False

    def delete(self, key: bytes) -> bool:
        mark, one, two = (int(x[0]) for x in self.places([key]))
        for bucket in (one, two):
            if len(own := np.flatnonzero(self.table[bucket] == mark)):
                self.table[bucket, own[0]] = 0
                return True
        return False

    def contains(self, keys: list[bytes]) -> np.ndarray:
        if not keys:
            return np.zeros(0, dtype=bool)
        mark, one, two = self.places(keys)
        hit = lambda b: (self.table[b.astype(np.int64)] == mark[:, None]).any(axis=1)
        return hit(one) | hit(two)


class ShardedFilters:
    """The filters of all shards; a key asks its own shard's only."""

    def __init__(self, dumps: dict[int, bytes], shards: int):
        self.shards, sizes = shards, np.zeros(shards, dtype=np.int64)
        tables = {k: np.frombuffer(v, dtype=np.uint16).reshape(-1, SLOTS) for k, v in dumps.items()}
        for k, t in tables.items():
            sizes[k] = len(t)
        self.sizes, self.start = sizes, np.cumsum(sizes) - sizes
        self.table = np.concatenate([np.zeros((0, SLOTS), dtype=np.uint16), *(tables[k] for k in sorted(tables))])

    def contains(self, keys: list[bytes]) -> np.ndarray:
        if not keys or not len(self.table):
            return np.zeros(len(keys), dtype=bool)
        raw = np.frombuffer(b"".join(keys), dtype=np.uint8).reshape(len(keys), -1)
        shard = shard_numbers(raw, self.shards)
        mark, low = marks(raw)
        size, start = self.sizes[shard], self.start[shard]
        last = np.maximum(size - 1, 0).astype(np.uint64)
        one = low & last
        two = (one ^ step_of(mark)) & last
        found = np.zeros(len(keys), dtype=bool)
        live = np.flatnonzero(size)
        for bucket in (one, two):
            found[live] |= (self.table[start[live] + bucket[live].astype(np.int64)] == mark[live, None]).any(axis=1)
        return found


def shard_numbers(raw: np.ndarray, shards: int) -> np.ndarray:
    """Shards of keys, the rows of ``raw``: their last four bytes modulo the number of shards."""
    return (raw[:, 12:16].copy().view(">u4").ravel().astype(np.int64)) % shards


def marks(raw: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(fingerprint, first eight bytes as a number) of keys."""
    mark = raw[:, 8:10].copy().view("<u2").ravel()
    return np.where(mark == 0, 1, mark).astype(np.uint16), raw[:, :8].copy().view("<u8").ravel()  # zero means empty


def step_of(mark: np.ndarray) -> np.ndarray:
    """From a fingerprint's bucket to its other one, by exclusive or."""
    return (np.asarray(mark, dtype=np.uint64) * np.uint64(0x5BD1E995)) >> np.uint64(7)
