"""SentencePiece encoding and decoding by a relational lattice.

Texts are normalised as the model says (identity with escaped spaces and a leading one) and cut where no piece reaches
across: between two characters that stand side by side in no piece. The distinct segments of all texts are a table. Each
segment's substrings of bounded length are exploded and equi-joined with the piece table; the matches, its lattice edges, are
grouped by segment, and a higher-order ``aggregate`` folds them into one path: for a unigram model Viterbi's best path by the sum of
scores, for a BPE model the merges in order of score, leftmost first, as the library does it (a best path by BPE scores would
be another result). Characters without a piece become byte pieces. The dictionary of segments is a written table.

Texts are then laid out where they lie, from a compact table of the most frequent segments: no more than ``dictionary_bytes``,
packed by tasks and passed on by the driver, whose memory it bounds. Texts that hold another segment leave as ids with gaps; their
missing segments meet the dictionary in a join, and the answers fill the gaps. A segment is known by 96 bits of two hashes in
the compact table, which takes segments of at most ``SHORT`` code points, and by its text in the join.

Segments of more than ``LONG`` code points are merged from the same edges with a heap in Python: the fold for BPE keeps a
segment's boundaries as the bits of one long. U+2581 in a text reads back as a space, as with the library.
"""

from __future__ import annotations

import heapq
from dataclasses import dataclass
from uuid import uuid4

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from dagframe.llm.common import read_table, release, with_checkpoints

MODEL = "piece_bpe_32k.model"
SPACE = "▁"
LONG, SHORT = 61, 255
DICTIONARY_BYTES = 64 << 20
ENTRY_BYTES = 23
GROUP = 1 << 18
ROWS = 500

_FACTOR, _OTHER = 0xD6E8FEB86659FD93, 0xA0761D6478BD642F
_models: dict = {}


def default_path() -> str:
    import public_tokenizers

    return public_tokenizers.path(MODEL)


def _fields(data: bytes):
    """(field number, value) of a serialised message."""
    at = 0

    def number() -> int:
        nonlocal at
        value = shift = 0
        while True:
            byte = data[at]
            at += 1
            value |= (byte & 127) << shift
            shift += 7
            if byte < 128:
                return value

    while at < len(data):
        key = number()
        if key & 7 == 0:
            yield key >> 3, number()
        else:
            size = number() if key & 7 == 2 else {5: 4, 1: 8}[key & 7]
            yield key >> 3, data[at : at + size]
            at += size


@dataclass
class PieceModel:
    """What the lattice needs of a model file."""

    bpe: bool
    pieces: list[str]
    scores: list[float]
    normal: list[bool]
    first_byte: int
    prefix: bool

    @classmethod
    def load(cls, path: str) -> PieceModel:
        if path not in _models:
            import sentencepiece

            own = sentencepiece.SentencePieceProcessor(model_file=path)
            parts = dict(_fields(own.serialized_model_proto()))
            trainer, rule, n = dict(_fields(parts[2])), dict(_fields(parts[3])), own.get_piece_size()
            if rule.get(1) != b"identity" or rule.get(4, 1):
                raise ValueError("only models with identity normalisation and kept white space are supported")
            plain = [not (own.is_control(i) or own.is_unknown(i) or own.is_byte(i) or own.is_unused(i)) for i in range(n)]
            first = next((i for i in range(n) if own.is_byte(i)), -1)
            _models[path] = cls(trainer.get(3, 1) == 2, [own.id_to_piece(i) for i in range(n)], [own.get_score(i) for i in range(n)], plain, first, bool(rule.get(3, 1)))
        return _models[path]

    def rows(self) -> list[tuple[str, int, float]]:
        return [(p, i, s) for i, (p, s, ok) in enumerate(zip(self.pieces, self.scores, self.normal, strict=True)) if ok]

    @property
    def longest(self) -> int:
        return max(len(p) for p, *_ in self.rows())


class Cutter:
    """Cuts texts between characters that no piece has side by side, and hashes the segments."""

    def __init__(self, model: PieceModel):
        pairs = {(a, b) for p, *_ in model.rows() for a, b in zip(p, p[1:], strict=False)}
        self.prefix = model.prefix
        self.single = np.full(0x110000, -1, dtype=np.int32)
        for p, i, _ in model.rows():
            if len(p) == 1:
                self.single[ord(p)] = i
        self.left, self.right = np.zeros(0x110000, dtype=np.int32), np.zeros(0x110000, dtype=np.int32)
        for side, at in ((self.left, 0), (self.right, 1)):
            for k, c in enumerate(sorted({p[at] for p in pairs})):
                side[ord(c)] = k + 1
        self.joined = np.zeros((self.left.max() + 1, self.right.max() + 1), dtype=bool)
        for a, b in pairs:
            self.joined[self.left[ord(a)], self.right[ord(b)]] = True
        self.powers: list[np.ndarray] = []
        self.cuts = 0

    def _grown(self, n: int) -> None:
        """Powers of both factors and of their inverses, modulo 2**64."""
        if not self.powers or len(self.powers[0]) < n:
            size = max(n, 2 * GROUP)
            self.powers = [np.cumprod(np.r_[np.uint64(1), np.full(size - 1, np.uint64(f), dtype=np.uint64)], dtype=np.uint64) for own in (_FACTOR, _OTHER) for f in (own, pow(own, -1, 1 << 64))]

    def cut(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """(code points of all texts, segments' starts with a last end, hashes, second hashes, each text's first segment with a last end)."""
        self.cuts += 1
        if self.cuts % 32 == 0:
            release()
        start = SPACE if self.prefix else ""
        whole = [start + t.replace(" ", SPACE) if t else "" for t in texts]
        points = np.frombuffer("".join(whole).encode("utf-32-le", "surrogatepass"), dtype=np.uint32)
        borders = np.r_[0, np.cumsum([len(w) for w in whole])].astype(np.int64)
        edge = np.ones(len(points) + 1, dtype=bool)
        edge[1:-1] = ~self.joined[self.left[points[:-1]], self.right[points[1:]]]
        edge[borders] = True
        at = np.flatnonzero(edge) if len(points) else np.zeros(1, dtype=np.int64)
        return points, at, *self.hashed(points, at), np.searchsorted(at, borders)

    def hashed(self, points: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """64 bits and 32 bits of two hashes of each segment."""
        self._grown(len(points) + 1)
        wide, sums = points.astype(np.uint64), np.zeros(len(points) + 1, dtype=np.uint64)
        np.cumsum((wide + np.uint64(1)) * self.powers[0][: len(points)], out=sums[1:])
        first = (sums[at[1:]] - sums[at[:-1]]) * self.powers[1][at[:-1]]
        np.cumsum((wide * np.uint64(0x9E3779B97F4A7C15) ^ np.uint64(0x2545F4914F6CDD1D)) * self.powers[2][: len(points)], out=sums[1:])
        second = (sums[at[1:]] - sums[at[:-1]]) * self.powers[3][at[:-1]]
        return first, (second >> np.uint64(32)).astype(np.uint32)


def _groups(texts: list[str]):
    """Index ranges of ``texts`` of about GROUP characters each."""
    at = size = 0
    for i, t in enumerate(texts):
        size += len(t)
        if size > GROUP:
            yield at, i + 1
            at, size = i + 1, 0
    if at < len(texts):
        yield at, len(texts)


class _Seen:
    """Hashes that were handed on, as sorted runs, each far longer than the next; forgotten when there are very many."""

    def __init__(self, most: int = 4_000_000):
        self.runs: list[tuple[np.ndarray, np.ndarray]] = []
        self.most = most

    def new(self, hashes: np.ndarray, checks: np.ndarray) -> np.ndarray:
        """Which of these, in rising order of hashes, are new; they are seen from now on."""
        fresh = np.ones(len(hashes), dtype=bool)
        for own, other in self.runs:
            at = np.minimum(np.searchsorted(own, hashes), len(own) - 1)
            fresh &= (own[at] != hashes) | (other[at] != checks)
        if fresh.any():
            self.runs.append((hashes[fresh], checks[fresh]))
        while len(self.runs) > 1 and 4 * len(self.runs[-1][0]) > len(self.runs[-2][0]):
            both = [np.concatenate(x) for x in zip(*self.runs[-2:], strict=True)]
            order = np.argsort(both[0], kind="stable")
            self.runs[-2:] = [(both[0][order], both[1][order])]
        if sum(len(x) for x, _ in self.runs) > self.most:
            self.runs = []
        return fresh


def segments(docs: DataFrame, text: str, model: PieceModel) -> DataFrame:
    """The distinct segments of all texts, in ``segment``, with the ids of their characters (-1: none) in ``singles`` and, in
    ``n``, about how often they occur.

    Each task hands on each of its own segments about once, with its number in the first texts that hold it.
    """
    small = len(model.pieces) < 1 << 15

    def run(batches):
        cutter, seen = Cutter(model), _Seen()
        for b in batches:
            texts = b.column(0).to_pylist()
            for s, e in _groups(texts):
                points, at, hashes, checks, _ = cutter.cut(texts[s:e])
                codes, own = pd.factorize(hashes)
                first = np.empty(len(own), dtype=np.int64)
                first[codes[::-1]] = np.arange(len(codes) - 1, -1, -1)
                other = np.flatnonzero(checks != checks[first][codes]) if len(codes) else codes  # another segment with the same first hash
                n = np.bincount(codes, minlength=len(own))
                rank = np.argsort(own)
                first = first[rank][seen.new(own[rank], checks[first[rank]])]
                first, n = np.r_[first, other], np.r_[n[codes[first]], np.ones(len(other), dtype=np.int64)]
                rows = [points[at[i] : at[i + 1]].tobytes().decode("utf-32-le", "surrogatepass") for i in first]
                sizes = at[first + 1] - at[first]
                past = np.r_[0, np.cumsum(sizes)]
                flat = cutter.single[points[np.repeat(at[first] - past[:-1], sizes) + np.arange(past[-1])]].astype(np.int16 if small else np.int32)
                yield pa.RecordBatch.from_arrays([pa.array(rows, pa.string()), pa.ListArray.from_arrays(pa.array(past.astype(np.int32)), pa.array(flat)), pa.array(n, pa.int64())], ["segment", "singles", "n"])
        release()

    found = docs.select(F.coalesce(F.col(text), F.lit("")).alias("t")).mapInArrow(run, f"segment string, singles array<{'smallint' if small else 'int'}>, n long")
    return found.groupBy("segment", "singles").agg(F.sum("n").alias("n"))  # the segment alone fixes its singles; as keys they are hashed, not sorted


@dataclass
class Packing:
    """How an edge of a BPE lattice stands in one long: level, start, length, id and whether it is early, from the highest bits
    down, so that edges sort by level, then start."""

    ids: int
    lengths: int
    starts: int

    @classmethod
    def of(cls, model: PieceModel) -> Packing:
        ids, lengths = len(model.pieces).bit_length(), max(2, model.longest).bit_length()
        return cls(ids, lengths, 62 - 2 * ids - lengths)

    def packed(self, level: str, start: str, length: str, piece: str, early: str) -> str:
        return f"shiftleft(shiftleft(shiftleft(shiftleft(cast({level} as bigint), {self.starts}) + {start}, {self.lengths}) + {length}, {self.ids}) + {piece}, 1) + if({early}, 1, 0)"

    def start(self, x: str) -> str:
        return f"cast(shiftright({x}, {self.ids + self.lengths + 1}) & {(1 << self.starts) - 1}L as int)"

    def length(self, x: str) -> str:
        return f"cast(shiftright({x}, {self.ids + 1}) & {(1 << self.lengths) - 1}L as int)"

    def piece(self, x: str) -> str:
        return f"cast(shiftright({x}, 1) & {(1 << self.ids) - 1}L as int)"

    def masks(self, x: str) -> str:
        """An edge with the boundaries within it, and these with both its ends, as bits."""
        within, all_ = f"shiftleft(1L, {self.length(x)} - 1) - 1L", f"shiftleft(1L, {self.length(x)} + 1) - 1L"
        return f"struct({x} as p, shiftleft({within}, {self.start(x)} + 1) as inner, shiftleft({all_}, {self.start(x)}) as span)"

    def unpacked(self, x: int) -> tuple[int, int, int, int]:
        """(level, start, end, id)."""
        s = x >> self.ids + self.lengths + 1 & (1 << self.starts) - 1
        return x >> self.ids + self.lengths + self.starts + 1, s, s + (x >> self.ids + 1 & (1 << self.lengths) - 1), x >> 1 & (1 << self.ids) - 1


def _early(model: PieceModel, levels: dict[float, int]) -> set[str]:
    """Pieces that merge before one of their two parts, at some place where they can be cut in two: after a merge, only these can
    be next although they come before it in the order of edges."""
    known = {p: levels[s] for p, _, s in model.rows()}
    part = lambda p: -1 if len(p) == 1 else known.get(p)
    halves = lambda p: ((part(p[:k]), part(p[k:])) for k in range(1, len(p)))
    return {p for p, own in known.items() if any(a is not None and b is not None and max(a, b) >= own for a, b in halves(p))}


def _merged() -> str:
    """Fold for BPE. State: the present boundaries as bits. An edge merges if it spans just two of the present parts: one boundary
    lies within it, and both its ends are there. A pass takes the edges in order, best first; a merge that makes an earlier
    one fit sets the sign, the rest of the pass does nothing, and another pass begins. Each merges something, so n are enough."""
    fits = lambda b, x: f"bit_count({b} & {x}.inner) = 1 and bit_count({b} & {x}.span) = 3"
    back = f"exists(early, y -> y.p < x.p and {fits('(b & ~x.inner)', 'y')})"
    step = f"if(b >= 0 and {fits('b', 'x')}, if({back}, (b & ~x.inner) | shiftleft(1L, 63), b & ~x.inner), b)"
    return f"aggregate(sequence(1, n), full | shiftleft(1L, 63), (a, k) -> if(a >= 0, a, aggregate(edges, a & {(1 << 63) - 1}L, (b, x) -> {step})))"


def _best_path(edges: str) -> str:
    """Fold for unigram: Viterbi over positions; each state is (score, boundaries so far) of the best path to it."""
    unknown = "struct(cast(k - 1 as int) as s, cast(-1e6 as double) as score)"
    reach = f"concat(transform(filter({edges}, x -> x.e = k), x -> struct(x.s as s, x.score as score)), array({unknown}))"
    best = f"array_max(transform({reach}, x -> struct(states[x.s].score + x.score as score, array_append(states[x.s].b, k) as b)))"
    return f"aggregate(sequence(1, n), array(struct(cast(0 as double) as score, array(0) as b)), (states, k) -> array_append(states, {best}))[n].b"


def encoded_segments(found: DataFrame, model: PieceModel) -> DataFrame:
    """``(segment, n, ids)``, the ids as array<int>, of the table that ``segments`` gives."""
    spark = found.sparkSession
    levels = {v: k for k, v in enumerate(sorted({s for *_, s in model.rows()}, reverse=True))}
    least = 2 if model.bpe else 1  # merges start from characters, which have their ids already
    pack, early = Packing.of(model), _early(model, levels) if model.bpe else set()
    table = spark.createDataFrame([("", 0, -1, 0.0, False), *((p, levels[s], i, s, p in early) for p, i, s in model.rows() if len(p) >= least)], "piece string, level int, id int, score double, early boolean")
    starts = found.select("segment", "singles", "n", F.explode(F.expr(f"sequence(0, greatest(0, length(segment) - {least}))")).alias("s"))
    first = f"if(s = 0, 0, {least})"  # the empty piece is there once, so that a segment without edges stays
    sizes = starts.select("*", F.explode(F.expr(f"sequence({first}, greatest({first}, least({model.longest}, length(segment) - s)))")).alias("m"))
    parts = sizes.select("segment", "singles", "n", "s", "m", F.expr("coalesce(substring(segment, s + 1, m), '')").alias("piece"))  # never null, so that no filter cuts it out once more
    edge = F.expr(pack.packed("level", "s", "m", "id", "early") if model.bpe else "struct(level, s, s + m as e, id, score)")
    edges = parts.join(F.broadcast(table), "piece").groupBy("segment", "singles", "n").agg(F.sort_array(F.collect_list(F.when(F.col("m") > 0, edge))).alias("wide"))
    sized = edges.withColumnRenamed("n", "seen").withColumn("n", F.length("segment"))
    single = lambda i: (
        f"if(singles[{i}] >= 0, array(cast(singles[{i}] as int)), transform(sequence(1, octet_length(substring(segment, {i} + 1, 1))), "
        f"k -> cast(conv(substring(hex(encode(substring(segment, {i} + 1, 1), 'utf-8')), 2 * k - 1, 2), 16, 10) as int) + {model.first_byte}))"
    )
    if not model.bpe:
        places = "transform(sequence(0, size(b) - 2), i -> struct(b[i] as s, b[i + 1] as e))"
        laid = F.expr(f"flatten(transform({places}, q -> if(q.e = q.s + 1, {single('q.s')}, array(filter(wide, w -> w.s = q.s and w.e = q.e)[0].id))))")
        return sized.withColumn("b", F.expr(_best_path("wide"))).select("segment", F.col("seen").alias("n"), laid.alias("ids"))

    @F.pandas_udf("array<int>")
    def heap(text: pd.Series, wide: pd.Series, singles: pd.Series) -> pd.Series:
        return pd.Series([None if t is None else _merge_long(t, [pack.unpacked(int(e)) for e in x], one, model) for t, x, one in zip(text, wide, singles, strict=True)], dtype=object)

    own = lambda c: F.when(F.col("n") > LONG, F.col(c))
    short = lambda e: F.when(F.col("n") <= LONG, F.expr(e))
    masks = sized.withColumn("edges", short(f"transform(wide, x -> {pack.masks('x')})")).withColumn("full", short("shiftleft(1L, n + 1) - 1L"))
    merged = masks.withColumn("early", short("filter(edges, x -> (x.p & 1L) = 1)")).withColumn("b", short(_merged()))
    kept = "filter(edges, x -> (b & x.inner) = 0 and bit_count(b & x.span) = 2)"
    begin = "filter(sequence(0, n - 1), i -> (shiftright(b, i) & 1L) = 1)"
    laid = f"flatten(transform({begin}, i -> if((shiftright(b, i + 1) & 1L) = 1, {single('i')}, transform(filter(kept, x -> {pack.start('x.p')} = i), x -> {pack.piece('x.p')}))))"
    both = merged.withColumn("kept", short(kept)).withColumn("folded", short(laid))
    return both.select("segment", F.col("seen").alias("n"), F.coalesce("folded", heap(own("segment"), own("wide"), own("singles"))).alias("ids"))


def _merge_long(text: str, edges: list[tuple[int, int, int, int]], singles: list, model: PieceModel) -> list[int]:
    """The same merges as the fold's, for long segments: neighbours in a linked list, candidates in a heap."""
    known = {(s, e): (level, i) for level, s, e, i in edges}
    after = list(range(1, len(text) + 2))
    before = list(range(-1, len(text) + 1))
    alive, queue = [True] * (len(text) + 1), []

    def offer(s: int) -> None:
        if 0 <= s < len(text) and after[s] < len(text) and (own := known.get((s, after[after[s]]))):
            heapq.heappush(queue, (own[0], s, after[after[s]]))

    for i in range(len(text)):
        offer(i)
    while queue:
        _, s, e = heapq.heappop(queue)
        if not alive[s] or after[s] >= len(text) or after[after[s]] != e:
            continue
        alive[after[s]] = False
        after[s] = e
        before[e] = s
        offer(s)
        offer(before[s])
    out, s = [], 0
    while s < len(text):
        if after[s] > s + 1:
            out.append(known[s, after[s]][1])
        else:
            out += [int(singles[s])] if singles[s] >= 0 else [model.first_byte + x for x in text[s].encode("utf-8", "surrogatepass")]
        s = after[s]
    return out


def encode(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", path: str | None = None, dictionary_bytes: int = DICTIONARY_BYTES, decoded: bool = False) -> DataFrame:
    """``(doc_id, ids)``, with ``decoded`` also the text that the ids read back as, of every row, without begin and end marks; null and empty texts have no ids; repeated rows stay.

    Segments go to all tasks in a compact table up to ``dictionary_bytes``, frequent ones first; texts that hold others are
    completed by a join. The ids are the same however many there are in the table.
    """
    model = PieceModel.load(path or default_path())
    spark = with_checkpoints(docs.sparkSession)
    known = _written(encoded_segments(segments(docs, text, model), model))
    slim = docs.select(F.col(doc_id).alias("doc_id"), F.coalesce(F.col(text), F.lit("")).alias("t"))
    frequent, all_ = _frequent(known, dictionary_bytes // ENTRY_BYTES)
    held = spark.sparkContext.broadcast(_compact(frequent, model))
    whole = _laid_out(slim, held, model, decoded)
    return whole if all_ else whole.unionByName(_completed(slim, known, held, model, decoded))


def _written(table: DataFrame) -> DataFrame:
    """``table`` as a Parquet table in the shared folder of checkpoints, which is far smaller than a checkpoint."""
    spark = table.sparkSession
    place = f"{spark.sparkContext.getCheckpointDir()}/table-{uuid4().hex}"
    table.write.parquet(place)
    return spark.read.schema(table.schema).parquet(place)


def _frequent(known: DataFrame, most: int) -> tuple[DataFrame, bool]:
    """About the ``most`` most frequent of the segments that a compact table takes, never more, and whether these are all segments."""
    level = F.floor(16 * F.log2(F.greatest("n", F.lit(1))))
    short = known.where(F.length("segment") <= SHORT)
    counts = {r["level"]: r["n"] for r in short.groupBy(level.alias("level")).agg(F.count("*").alias("n")).collect()}  # some hundreds of levels
    if sum(counts.values()) <= most:
        return short, short.count() == known.count()
    room, least, share = most, 1 << 30, 0
    for at in sorted(counts, reverse=True):
        if counts[at] > room:
            share = max(0, int(1000 * room / counts[at]) - 50)  # of a level that doesn't fit, by hash; a little less than fits
            break
        room, least = room - counts[at], at
    some = (level < least) & (level >= at) & (F.pmod(F.xxhash64("segment"), F.lit(1000)) < share)
    return short.where((level >= least) | some), False


def _compact(frequent: DataFrame, model: PieceModel) -> tuple[np.ndarray, ...]:
    """(hashes in rising order, second hashes, numbers of ids, places of the ids, ids); tasks pack them, the driver puts them in order."""
    kind = np.uint16 if len(model.pieces) <= 1 << 16 else np.int32

    def pack(batches):
        cutter = Cutter(model)
        for b in batches:
            words, ids = b.column(0).to_pylist(), b.column(1)
            points = np.frombuffer("".join(words).encode("utf-32-le", "surrogatepass"), dtype=np.uint32)
            hashes, checks = cutter.hashed(points, np.r_[0, np.cumsum([len(w) for w in words])].astype(np.int64))
            sizes, flat = np.diff(ids.offsets.to_numpy()), ids.flatten().to_numpy(zero_copy_only=False)
            yield pa.RecordBatch.from_arrays([pa.array([x.tobytes()], pa.binary()) for x in (hashes, checks, sizes.astype(np.uint16), flat.astype(kind))], ["h", "c", "s", "i"])
        release()

    rows = frequent.select("segment", "ids").mapInArrow(pack, "h binary, c binary, s binary, i binary").toArrow()
    columns = [np.frombuffer(b"".join(rows[k].to_pylist()), dtype=t) for k, t in (("h", np.uint64), ("c", np.uint32), ("s", np.uint16), ("i", kind))]
    del rows
    hashes, checks, sizes, pool = columns
    order = np.argsort(hashes, kind="stable")
    at = (np.cumsum(sizes, dtype=np.int64) - sizes).astype(np.uint32 if len(pool) < 1 << 32 else np.int64)
    made = hashes[order], checks[order], sizes[order], at[order], pool
    del columns, order
    release()
    return made


def _looked_up(own: Cutter, table: tuple[np.ndarray, ...], texts: list[str]):
    """(code points, starts, place of each segment in the compact table or -1, each text's first segment)."""
    points, at, hashes, checks, borders = own.cut(texts)
    codes, distinct = pd.factorize(hashes)
    if not len(codes) or not len(table[0]):
        return points, at, np.full(len(codes), -1), borders
    rank = np.argsort(distinct)
    place = np.empty(len(distinct), dtype=np.int64)
    place[rank] = np.minimum(np.searchsorted(table[0], distinct[rank]), len(table[0]) - 1)
    which = place[codes]
    return points, at, np.where((table[0][which] == hashes) & (table[1][which] == checks), which, -1), borders


def _lay(table: tuple[np.ndarray, ...], which: np.ndarray, gaps: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """(ids of all segments in a row, where each segment's begin with a last end); a gap is one id, its negative number."""
    _, _, sizes_, at_, pool = table
    if not len(which) or not len(at_):
        flat = np.zeros(0, dtype=np.int32) if gaps is None else gaps.astype(np.int32)
        return flat, np.arange(len(flat) + 1)
    sizes = np.where(which >= 0, sizes_[which], 1).astype(np.int64)
    past = np.r_[0, np.cumsum(sizes)]
    start = np.where(which >= 0, at_[which].astype(np.int64), 0)
    source = np.repeat(start - past[:-1], sizes) + np.arange(past[-1])
    flat = pool[np.minimum(source, len(pool) - 1)].astype(np.int32)
    if gaps is not None:
        flat[past[:-1][which < 0]] = gaps[which < 0]
    return flat, past


def _laid_out(slim: DataFrame, held, model: PieceModel, decoded: bool) -> DataFrame:
    """Rows all of whose segments are in the compact table."""

    def run(batches):
        own, text, table = Cutter(model), _decoder(model), held.value
        for b in (whole.slice(i, ROWS) for whole in batches for i in range(0, len(whole), ROWS)):
            texts, kept, n_ids, flats = b.column(1).to_pylist(), [], [], []
            for s, e in _groups(texts):
                _, _, which, borders = _looked_up(own, table, texts[s:e])
                lost = np.r_[0, np.cumsum(which < 0)]
                fits = lost[borders[1:]] == lost[borders[:-1]]
                mine = np.repeat(fits, np.diff(borders))
                flat, past = _lay(table, which[mine])
                size = np.diff(np.r_[0, np.cumsum(np.diff(borders)[fits])])
                n_ids.append(np.diff(past[np.r_[0, np.cumsum(size)]]))
                flats.append(flat)
                kept.append(np.flatnonzero(fits) + s)
            rows = np.concatenate(kept) if kept else np.zeros(0, dtype=np.int64)
            lengths = np.r_[0, np.cumsum(np.concatenate(n_ids))] if n_ids else np.zeros(1, dtype=np.int64)
            flat = np.concatenate(flats) if flats else np.zeros(0, dtype=np.int32)
            out = [b.column(0).take(pa.array(rows)), pa.ListArray.from_arrays(pa.array(lengths.astype(np.int32)), pa.array(flat))]
            if decoded:
                out.append(pa.array([text(flat[i:j]) for i, j in zip(lengths[:-1].tolist(), lengths[1:].tolist(), strict=True)], pa.string()))
            yield pa.RecordBatch.from_arrays(out, ["doc_id", "ids", "decoded"][: len(out)])
        release()

    return slim.mapInArrow(run, _shape(slim, decoded))


def _shape(slim: DataFrame, decoded: bool) -> str:
    return f"doc_id {slim.schema['doc_id'].dataType.simpleString()}, ids array<int>{', decoded string' if decoded else ''}"


def _completed(slim: DataFrame, known: DataFrame, held, model: PieceModel, decoded: bool) -> DataFrame:
    """Rows with segments that the compact table lacks: ids with gaps, compressed, meet the ids of what is missing."""
    import zstandard

    def mark(batches):
        own, table, pack = Cutter(model), held.value, zstandard.ZstdCompressor(3)
        for b in batches:
            ids, texts, rows = b.column(0), b.column(1).to_pylist(), ([], [], [])
            for i, t in enumerate(texts):
                points, at, which, _ = _looked_up(own, table, [t])
                if (gone := np.flatnonzero(which < 0)).size:
                    words = [points[at[k] : at[k + 1]].tobytes().decode("utf-32-le", "surrogatepass") for k in gone]
                    number = {w: n for n, w in enumerate(dict.fromkeys(words))}
                    gaps = np.zeros(len(which), dtype=np.int64)
                    gaps[gone] = [-1 - number[w] for w in words]
                    for column, value in zip(rows, (i, pack.compress(_lay(table, which, gaps)[0].astype("<i4").tobytes()), list(number)), strict=True):
                        column.append(value)
            yield pa.RecordBatch.from_arrays([ids.take(pa.array(rows[0], pa.int64())), pa.array(rows[1], pa.binary()), pa.array(rows[2], pa.list_(pa.string()))], ["doc_id", "packed", "lost"])
        release()

    kind = slim.schema["doc_id"].dataType.simpleString()
    marked = _written(slim.mapInArrow(mark, f"doc_id {kind}, packed binary, lost array<string>").withColumn("row", F.monotonically_increasing_id()))
    asked = marked.select("row", F.posexplode("lost").alias("pos", "segment")).join(known.select("segment", "ids"), "segment")
    answers = asked.groupBy("row").agg(F.sort_array(F.collect_list(F.struct("pos", "ids"))).alias("found"))  # no more than a text's own segments
    both = marked.select("row", "doc_id", "packed").join(answers, "row").select("doc_id", "packed", F.col("found.ids").alias("found"))

    def fill(batches):
        open_, text = zstandard.ZstdDecompressor(), _decoder(model)
        for b in batches:
            out: tuple[list, list] = ([], [])
            for data, found in zip(b.column(1).to_pylist(), b.column(2).to_pylist(), strict=True):
                flat = np.frombuffer(open_.decompress(data), dtype="<i4")
                parts = [np.array(x, dtype=np.int32) for x in found]
                n = np.array([len(x) for x in parts], dtype=np.int64)
                first, pool = np.cumsum(n) - n, np.concatenate(parts)
                gap = flat < 0
                sizes = np.ones(len(flat), dtype=np.int64)
                sizes[gap] = n[-1 - flat[gap]]
                past = np.cumsum(sizes) - sizes
                made = np.repeat(flat, sizes)
                inside = np.repeat(gap, sizes)
                made[inside] = pool[(np.repeat(np.where(gap, first[np.where(gap, -1 - flat, 0)], 0) - past, sizes) + np.arange(len(made)))[inside]]
                out[0].append(made)
                out[1].append(text(made) if decoded else None)
            columns = [b.column(0), pa.array(out[0], pa.list_(pa.int32())), pa.array(out[1], pa.string())]
            yield pa.RecordBatch.from_arrays(columns[: 2 + decoded], ["doc_id", "ids", "decoded"][: 2 + decoded])
        release()

    return both.mapInArrow(fill, _shape(slim, decoded))


def _decoder(model: PieceModel):
    """A function from an array of ids to their text."""
    data = [bytes([i - model.first_byte]) if model.first_byte <= i < model.first_byte + 256 else p.replace(SPACE, " ").encode() if ok else b"" for i, (p, ok) in enumerate(zip(model.pieces, model.normal, strict=True))]
    sizes = np.array([len(x) for x in data], dtype=np.int64)
    begins, pool, start = np.cumsum(sizes) - sizes, np.frombuffer(b"".join(data), dtype=np.uint8), b" " if model.prefix else b""

    def text(ids: np.ndarray) -> str:
        n = sizes[ids]
        past = np.cumsum(n)
        return pool[np.repeat(begins[ids] - (past - n), n) + np.arange(past[-1] if len(n) else 0)].tobytes().removeprefix(start).decode("utf-8", "replace")

    return text


def decode(rows: DataFrame, ids: str = "ids", out: str = "decoded", path: str | None = None) -> DataFrame:
    """``rows`` with the text of ``ids`` in ``out``: pieces in order, byte pieces as UTF-8, without the leading space."""
    text = _decoder(PieceModel.load(path or default_path()))

    @F.pandas_udf("string")
    def run(column: pd.Series) -> pd.Series:
        return pd.Series([text(np.asarray(x if x is not None else (), dtype=np.int64)) for x in column], dtype=object)

    return rows.withColumn(out, run(ids))


def op2_sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ids of every document, their number, and the digest of the text that they read back as."""
    return encode(read_table(spark, sf_dir, "documents"), decoded=True).select("doc_id", F.size("ids").cast("long").alias("n_pieces"), "ids", F.sha2("decoded", 256).alias("decoded_sha256"))
