"""Personalised PageRank by push, plain and on attribute-weighted edges."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from attrgraph.operators.attributes import WIDE, as_vectors
from attrgraph.operators.diffusion import ALPHA, diffuse, scores, start_unit
from attrgraph.operators.graph import EDGE_COLUMNS, Graph
from attrgraph.operators.sharing import SharedGraph


def seeded_pagerank(g: Graph, seeds: DataFrame, alpha: float = ALPHA, eps: float = 1e-4, **options) -> DataFrame:
    """(seed_id, node_id, score): threshold-push reserve over degree."""
    state = diffuse(g, start_unit(seeds), alpha, eps, "threshold", **options)
    return scores(state).select("seed_id", "node_id", (F.col("score") / F.col("deg")).alias("score"))


def attr_weighted_graph(g: Graph, attrs: DataFrame, bandwidth: float = 1.0) -> Graph:
    """Edge weights exp(-|x_i - x_j|^2 / (2 h^2)) of tall attribute rows; a missing row is all zeros."""
    if isinstance(g, SharedGraph) and attrs.select("attr").distinct().count() <= WIDE:
        held = g._parts.get("weighted")
        if held is None or held[0] is not attrs or held[1] != bandwidth:
            held = g._parts["weighted"] = (attrs, bandwidth, g.by_rows(as_vectors(attrs), float(bandwidth)))
        return held[2]
    pairs = g.edges.select("src", "dst").where("src < dst")
    left, right = attrs.select(F.col("node_id").alias("src"), "attr", F.col("value").alias("v")), attrs.select(F.col("node_id").alias("dst"), "attr", F.col("value").alias("u"))
    shared = pairs.join(left, "src").join(right, ["dst", "attr"]).groupBy("src", "dst").agg(F.sum(F.col("v") * F.col("u")).alias("dot"))
    norm = attrs.groupBy("node_id").agg(F.sum(F.col("value") * F.col("value")).alias("q"))
    zero = F.lit(0.0)
    rows = pairs.join(shared, ["src", "dst"], "left")
    rows = rows.join(norm.select(F.col("node_id").alias("src"), F.col("q").alias("q1")), "src", "left").join(norm.select(F.col("node_id").alias("dst"), F.col("q").alias("q2")), "dst", "left")
    gap = F.greatest(zero, F.coalesce("q1", zero) + F.coalesce("q2", zero) - 2 * F.coalesce("dot", zero))
    weighted = rows.select(F.col("src").alias("a"), F.col("dst").alias("b"), F.exp(-gap / (2 * bandwidth * bandwidth)).alias("w"))
    both = weighted.select(F.explode(F.array(F.struct(F.col("a").alias("src"), F.col("b").alias("dst"), "w"), F.struct(F.col("b").alias("src"), F.col("a").alias("dst"), "w"))).alias("e")).select("e.*")
    degree = both.groupBy("src").agg(F.sum("w").alias("src_deg"))
    return Graph(both.join(degree, "src").join(degree.select(F.col("src").alias("dst"), F.col("src_deg").alias("dst_deg")), "dst").select(*EDGE_COLUMNS), whole=g.whole)


def attr_weighted_pagerank(g: Graph, attrs: DataFrame, seeds: DataFrame, bandwidth: float = 1.0, **options) -> DataFrame:
    return seeded_pagerank(attr_weighted_graph(g, attrs, bandwidth), seeds, **options)
