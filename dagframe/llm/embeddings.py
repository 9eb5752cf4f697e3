"""Embedding near-dedup by a forest of random-projection trees.

Every tree splits the unit vectors by random directions at the median, again and again; a vector close to a split goes to
both sides (spill), so near vectors seldom part, and a pair that parts in one tree meets in another. The trees are fitted on
a bounded sample of rows (``sample``, 20,000) and sent to all tasks; every vector is dealt to all its leaves. Vectors are
compared within leaves, in double precision, and a pair counts if its cosine reaches the threshold; nothing else links.
Each row carries the list of its leaves, so a pair counts in the first leaf only that it shares: a leaf gives sums and a
spanning forest, never pairs. A leaf with more than ``CELL`` rows, such as that of a tight group which planes can't split, is cut
into a grid of cells, each a pair of its parts, which are compared in tasks of their own. Vectors travel as they came (in
single precision if they were given so) and are scaled in double precision where they are compared. Vectors that are exactly
equal are one class from the start and take no part in the search.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from dagframe.llm.common import partitions_of, read_table, release, with_checkpoints
from dagframe.llm.components import components

THRESHOLD = 0.95
TREES = 6
SPILL = 0.2
LEAF = 512
SAMPLE = 20_000
DEPTH = 20
CELL = 4096
SEED = 11


def unit(x: np.ndarray) -> np.ndarray:
    """Rows of ``x`` in double precision, scaled to length one; they must be finite and not zero."""
    x = x.astype(np.float64)
    x = x / np.abs(x).max(axis=1, keepdims=True)  # lengths of huge or tiny components stay finite
    return x / np.sqrt((x * x).sum(axis=1, keepdims=True))


class Split:
    """One split: a direction, its cut and the width on both sides of it in which a vector goes both ways."""

    def __init__(self, x: np.ndarray, random: np.random.Generator, spill: float):
        way = random.standard_normal(x.shape[1])
        self.way = way / np.linalg.norm(way)
        along = x @ self.way
        self.cut = float(np.median(along))
        self.width = spill * float(along.std())

    def sides(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        off = x @ self.way - self.cut
        return off <= self.width, off > -self.width


def grow(x: np.ndarray, levels: int, random: np.random.Generator, spill: float, least: int = 8) -> list:
    """A tree as nested lists [split, left, right]; a leaf is []."""
    if not levels or len(x) < least:
        return []
    split = Split(x, random, spill)
    left, right = split.sides(x)
    if left.all() or right.all():
        return []
    return [split, grow(x[left], levels - 1, random, spill, least), grow(x[right], levels - 1, random, spill, least)]


def route(x: np.ndarray, tree: list, at: np.ndarray, number: int = 1):
    """(leaf number, rows) for all leaves of ``tree`` that rows of ``x`` reach."""
    if not len(at):
        return
    if not tree:
        yield number, at
        return
    left, right = tree[0].sides(x[at])
    yield from route(x, tree[1], at[left], 2 * number)
    yield from route(x, tree[2], at[right], 2 * number + 1)


class Places:
    """The leaves of every row of a leaf, as sorted numbers: tells whether two rows met in an earlier leaf."""

    def __init__(self, lists: list[bytes], leaf: int):
        each = [np.frombuffer(x, dtype=np.int32) for x in lists]
        sizes = np.array([np.searchsorted(x, leaf) for x in each], dtype=np.int64)  # those before this leaf
        self.sizes, self.start = sizes, np.cumsum(sizes) - sizes
        values = np.concatenate([x[:n] for x, n in zip(each, sizes, strict=True)]).astype(np.int64) if len(each) else np.zeros(0, dtype=np.int64)
        self.values, self.keys = values, np.repeat(np.arange(len(each), dtype=np.int64), sizes) << 32 | values

    def met(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        n = self.sizes[a]
        if not len(self.keys) or not n.sum():
            return np.zeros(len(a), dtype=bool)
        pair = np.repeat(np.arange(len(a)), n)
        value = self.values[np.repeat(self.start[a] - (np.cumsum(n) - n), n) + np.arange(n.sum())]
        key = b[pair] << 32 | value
        at = np.minimum(np.searchsorted(self.keys, key), len(self.keys) - 1)
        return np.bincount(pair[self.keys[at] == key], minlength=len(a)) > 0


def _joined(label: np.ndarray, a: np.ndarray, b: np.ndarray) -> list[int]:
    """Positions of links that join two parts of ``label``, which is updated; no more than parts joined."""
    differ = np.flatnonzero(label[a] != label[b])
    if not len(differ):
        return []
    low, high = np.minimum(label[a[differ]], label[b[differ]]), np.maximum(label[a[differ]], label[b[differ]])
    _, first = np.unique(low * len(label) + high, return_index=True)
    root: dict[int, int] = {}

    def find(i: int) -> int:
        while root.get(i, i) != i:
            i = root[i]
        return i

    out = []
    for k in first.tolist():
        x, y = find(int(low[k])), find(int(high[k]))
        if x != y:
            root[max(x, y)] = min(x, y)
            out.append(int(differ[k]))
    move = np.arange(len(label))
    for i in root:
        move[i] = find(i)
    label[:] = move[label]
    return out


def leaf_links(x: np.ndarray, n: np.ndarray, places: Places, threshold: float, split: int | None = None, block: int = 512) -> tuple[np.ndarray, list[tuple[int, int]]]:
    """(for each row the copies that it links with for the first time here, links that span the parts).

    All rows are compared with one another, or, with ``split``, those before that place with those from there on.
    """
    counts, label, edges = np.zeros(len(x)), np.arange(len(x)), []
    left, right = (len(x), 0) if split is None else (split, split)
    for i in range(0, left, block):
        for j in range(i if split is None else right, len(x), block):
            end = min(i + block, left)
            a, b = np.nonzero(x[i:end] @ x[j : j + block].T >= threshold)
            a, b = a + i, b + j
            if i == j:
                a, b = a[a < b], b[a < b]
            if len(a):
                new = ~places.met(a, b)
                a, b = a[new], b[new]
                counts += np.bincount(a, weights=n[b], minlength=len(x)) + np.bincount(b, weights=n[a], minlength=len(x))
                edges += [(int(a[k]), int(b[k])) for k in _joined(label, a, b)]
    return counts, edges


def near_links(classes: DataFrame, vector: str = "vector", node: str = "node", size: str = "n", threshold: float = THRESHOLD, trees: int = TREES, spill: float = SPILL, leaf: int = LEAF, sample: int = SAMPLE, cell: int = CELL, kind: str = "<f8") -> DataFrame:
    """``(a, b, n)`` over nodes with vectors of one dimension, one row each; ``kind`` is the type that vectors travel in.

    Rows without b: n rows (by ``size``) link with node a, each counted in the first leaf only that the two share. Rows with b:
    links that span the components. Pairs themselves never leave their cell.
    """
    spark, parts = classes.sparkSession, partitions_of(classes.sparkSession)
    count = classes.count()
    levels = min(DEPTH, max(0, int(np.ceil(np.log2(max(1, count) / leaf)))))
    some = classes.orderBy(F.xxhash64(vector)).limit(sample).select(vector).toArrow() if levels else None
    random = np.random.default_rng(SEED)
    fitted = unit(np.array(some.column(0).to_pylist(), dtype=np.float64)) if levels and some.num_rows else None
    forest = spark.sparkContext.broadcast([grow(fitted, levels, random, spill) if fitted is not None else [] for _ in range(trees)])
    slim = classes.select(F.col(node).cast("long").alias("node"), F.col(vector).alias("v"), F.col(size).cast("long").alias("n"))

    def leaves_of(x: np.ndarray) -> list[tuple[int, np.ndarray]]:
        return [(t << DEPTH + 1 | number, at) for t, tree in enumerate(forest.value) for number, at in route(x, tree, np.arange(len(x)))]

    def weigh(batches):
        total: dict[int, int] = {}
        for b in batches:
            for k, at in leaves_of(unit(np.array(b.column(0).to_pylist(), dtype=np.float64))):
                total[k] = total.get(k, 0) + len(at)
        yield pa.RecordBatch.from_arrays([pa.array(list(total), pa.int32()), pa.array(list(total.values()), pa.int64())], ["leaf", "rows"])
        release()

    sizes = slim.select("v").mapInArrow(weigh, "leaf int, rows long").groupBy("leaf").agg(F.sum("rows").alias("rows"))
    wide = {r["leaf"]: -(-r["rows"] // cell) for r in sizes.where(F.col("rows") > cell).collect()}  # no more than the forest's leaves

    def deal(batches):
        for b in batches:
            raw = np.array(b.column(1).to_pylist(), dtype=np.float64)
            reached = leaves_of(unit(raw))
            rows, leaves = np.concatenate([at for _, at in reached]), np.concatenate([np.full(len(at), k) for k, at in reached]).astype(np.int32)
            order = np.lexsort((leaves, rows))
            cuts = np.searchsorted(rows[order], np.arange(len(raw) + 1))
            lists = [leaves[order][i:j].tobytes() for i, j in zip(cuts[:-1], cuts[1:], strict=True)]
            data = [r.tobytes() for r in raw.astype(kind)]
            ids = b.column(0).to_numpy().astype(np.uint64)
            for k, at in reached:
                grid = wide.get(k, 1)
                own = ((ids[at] * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(33)).astype(np.int64) % grid
                for other in range(grid):
                    low, high = np.minimum(own, other), np.maximum(own, other)
                    take = pa.array(at)
                    yield pa.RecordBatch.from_arrays(
                        [pa.array(np.full(len(at), k, dtype=np.int32)), pa.array(low * grid + high), pa.array(own != low), b.column(0).take(take), b.column(2).take(take), pa.array([data[i] for i in at], pa.binary()), pa.array([lists[i] for i in at], pa.binary())],
                        ["leaf", "cell", "second", "node", "n", "x", "leaves"],
                    )
        release()

    dealt = slim.mapInArrow(deal, "leaf int, cell long, second boolean, node long, n long, x binary, leaves binary")
    grouped = dealt.repartition(parts, "leaf", "cell").sortWithinPartitions("leaf", "cell", "second")

    def compare(batches):
        held: list = []

        def finish():
            node, n, x = (np.concatenate([h[c] for h in held]) for c in (1, 2, 3))
            second, (leaf_, cell_) = np.concatenate([h[5] for h in held]), held[0][0]
            places = Places([v for h in held for v in h[4]], leaf_)
            held.clear()
            grid = wide.get(leaf_, 1)
            counts, edges = leaf_links(unit(x), n, places, threshold, None if cell_ // grid == cell_ % grid else int((~second).sum()))
            some = np.flatnonzero(counts)
            a = np.concatenate([node[some], node[[e[0] for e in edges]]])
            b = pa.array([None] * len(some) + node[[e[1] for e in edges]].tolist(), pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array(a), b, pa.array(np.concatenate([counts[some], np.zeros(len(edges))]).astype(np.int64))], ["a", "b", "n"])

        for b in batches:
            if not len(b):
                continue
            leaf_, cell_ = b.column(0).to_numpy(), b.column(1).to_numpy()
            second, node, n = b.column(2).to_numpy(zero_copy_only=False), b.column(3).to_numpy(), b.column(4).to_numpy()
            x, lists = np.frombuffer(b"".join(b.column(5).to_pylist()), dtype=kind).reshape(len(b), -1), b.column(6).to_pylist()
            edge = np.r_[0, np.flatnonzero(np.diff(leaf_) | np.diff(cell_)) + 1, len(leaf_)]
            for s, e in zip(edge[:-1], edge[1:], strict=True):
                key = int(leaf_[s]), int(cell_[s])
                if held and held[0][0] != key:
                    yield from finish()
                held.append((key, node[s:e], n[s:e], x[s:e], lists[s:e], second[s:e]))
        if held:
            yield from finish()
        release()

    return grouped.mapInArrow(compare, "a long, b long, n long")


def near_duplicates(rows: DataFrame, vec_id: str = "vec_id", vector: str = "embedding", **options) -> DataFrame:
    """``(vec_id, n_links, component_id, kept)`` of every row.

    Vectors that are null, empty or zero, or that hold null or non-finite components, link with nothing and are kept.
    Vectors of different dimensions never link. A repeated vec_id is a row of its own, linked with its copies; a null
    vec_id links like any other, is never a component's name, and is kept only in a component without ids.
    """
    spark = with_checkpoints(rows.sparkSession)
    numbers = F.transform(F.col(vector), lambda v: v.cast("double"))
    sound = F.coalesce(F.size("v") > 0, F.lit(False)) & F.coalesce(F.forall("v", lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) < float("inf"))), F.lit(False)) & F.coalesce(F.exists("v", lambda v: v != 0), F.lit(False))
    plus = F.transform("v", lambda v: F.when(v == 0, F.lit(0.0)).otherwise(v))  # -0.0 and 0.0 are equal
    own = rows.select(F.col(vec_id).alias("vec_id"), numbers.alias("v")).withColumn("sound", sound).withColumn("vector", F.when(F.col("sound"), plus)).drop("v")
    hashes = {"h1": F.xxhash64("vector"), "h2": F.xxhash64(F.lit(7), "vector")}  # 128 bits name a vector
    classes = own.where("sound").groupBy("vector").agg(F.count("*").alias("n"), F.min("vec_id").alias("least")).withColumns(hashes | {"node": F.monotonically_increasing_id()}).checkpoint()
    dimensions = [r["d"] for r in classes.select(F.size("vector").alias("d")).distinct().collect()]
    kind = "<f4" if "array<float>" == rows.schema[vector].dataType.simpleString() else "<f8"
    found = spark.createDataFrame([], "a long, b long, n long")
    for d in dimensions:
        found = found.unionByName(near_links(classes.where(F.size("vector") == d), kind=kind, **options))
    found = found.checkpoint()
    sized = classes.select("node", "n", "least", "h1", "h2")
    links = found.where("b is null").groupBy("a").agg(F.sum("n").alias("others"))
    rooted = sized.join(components(found.where("b is not null")).withColumnRenamed("id", "node"), "node", "left").withColumn("root", F.coalesce("component", "node"))
    named = rooted.join(rooted.groupBy("root").agg(F.min("least").alias("component_id")), "root")
    each = named.join(links.withColumnRenamed("a", "node"), "node", "left").select("h1", "h2", (F.coalesce("others", F.lit(0)) + F.col("n") - 1).alias("n_links"), "component_id")
    joined = own.withColumns({k: F.when(F.col("sound"), v) for k, v in hashes.items()}).drop("vector").join(each, ["h1", "h2"], "left")
    group = F.when(F.col("sound"), F.col("component_id")).otherwise(F.col("vec_id"))
    return joined.select("vec_id", F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), group.alias("component_id"), F.col("vec_id").eqNullSafe(group).alias("kept"))


def op6_embedding_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Links, component and decision for every embedding."""
    return near_duplicates(read_table(spark, sf_dir, "embeddings"))
