"""Explainable item-to-item links: strongest links, scores carried along links, explanations, ego graphs, degree profiles."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def top_links(edges: DataFrame, nodes: DataFrame, m: int = 10) -> DataFrame:
    """The ``m`` strongest links with labels; of equals the smaller ids."""
    best = edges.orderBy(F.desc("w"), "src", "dst").limit(m)
    at = lambda end: nodes.select(F.col("node_id").alias(end), F.col("label").alias(f"{end}_label"))
    return best.join(at("src"), "src", "left").join(at("dst"), "dst", "left").select("src", "src_label", "dst", "dst_label", "w")


def contributions(cells: DataFrame, edges: DataFrame) -> DataFrame:
    """``(sample_id, node_id, via, part)``: what each of a sample's items adds to each linked item."""
    return cells.join(edges, cells["node_id"] == edges["src"]).select("sample_id", F.col("dst").alias("node_id"), F.col("src").alias("via"), (F.col("x") * F.col("w")).alias("part"))


def score(cells: DataFrame, edges: DataFrame, exclude_seen: bool = True, hops: int = 1) -> DataFrame:
    """``(sample_id, node_id, score)``: centred values carried along links; a positive score is a like."""
    now, total = cells, None
    for _ in range(hops):
        now = contributions(now, edges).groupBy("sample_id", "node_id").agg(F.sum("part").alias("x"))
        total = now if total is None else total.unionByName(now)
    out = total.groupBy("sample_id", "node_id").agg(F.sum("x").alias("score"))
    return out.join(cells.select("sample_id", "node_id"), ["sample_id", "node_id"], "left_anti") if exclude_seen else out


def explain(cells: DataFrame, edges: DataFrame, top: int = 3) -> DataFrame:
    """The ``top`` items behind each score, by absolute part: ``(sample_id, node_id, nth, via, part)``."""
    order = Window.partitionBy("sample_id", "node_id").orderBy(F.desc(F.abs("part")), "via")
    return contributions(cells, edges).withColumn("nth", F.row_number().over(order)).where(F.col("nth") <= top).select("sample_id", "node_id", "nth", "via", "part")


def explain_map(cells: DataFrame, edges: DataFrame) -> DataFrame:
    """``(sample_id, node_id, parts)``: all parts as a map from item to part, signs kept."""
    return contributions(cells, edges).groupBy("sample_id", "node_id").agg(F.map_from_entries(F.collect_list(F.struct("via", "part"))).alias("parts"))


def ego_graph(edges: DataFrame, node: int, radius: int = 1, m: int | None = None) -> DataFrame:
    """``(src, dst, w, sign)``: the links within ``radius`` steps of a node in either direction; the ``m`` strongest if given."""
    near = edges.sparkSession.createDataFrame([(node,)], "node long")
    for _ in range(radius):
        out = edges.join(near.select(F.col("node").alias("src")), "src", "left_semi").select(F.col("dst").cast("long").alias("node"))
        inn = edges.join(near.select(F.col("node").alias("dst")), "dst", "left_semi").select(F.col("src").cast("long").alias("node"))
        near = near.unionByName(out).unionByName(inn).distinct()
    kept = edges.join(near.select(F.col("node").alias("src")), "src", "left_semi").join(near.select(F.col("node").alias("dst")), "dst", "left_semi")
    kept = kept.select("src", "dst", "w", F.signum("w").cast("int").alias("sign"))
    return kept.orderBy(F.desc(F.abs("w")), "src", "dst").limit(m) if m else kept


def degree_profile(edges: DataFrame, popularity: DataFrame) -> DataFrame:
    """``(node_id, in_degree, out_degree, popularity)`` of every node that has a popularity or a link."""
    ends = edges.select(F.explode(F.array(F.struct(F.col("src").alias("node_id"), F.lit(0).alias("i"), F.lit(1).alias("o")), F.struct(F.col("dst").alias("node_id"), F.lit(1).alias("i"), F.lit(0).alias("o")))).alias("x"))
    n = ends.groupBy(F.col("x.node_id").alias("node_id")).agg(F.sum("x.i").alias("in_degree"), F.sum("x.o").alias("out_degree"))
    return popularity.join(n, "node_id", "full").select("node_id", F.coalesce("in_degree", F.lit(0)).alias("in_degree"), F.coalesce("out_degree", F.lit(0)).alias("out_degree"), F.coalesce("popularity", F.lit(0)).alias("popularity"))


def degree_correlation(profile: DataFrame) -> DataFrame:
    """How degrees go with popularity: hubs point outward, niche items are pointed at, or the reverse."""
    return profile.agg(F.corr("in_degree", "popularity").alias("in_corr"), F.corr("out_degree", "popularity").alias("out_corr"), F.max("in_degree").alias("most_in"), F.max("out_degree").alias("most_out"))
