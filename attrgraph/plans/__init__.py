"""Physical choices for a diffusion round that Catalyst can't make: what to broadcast, which buckets to read."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from attrgraph.operators.graph import Graph
from attrgraph.session import discard, materialise
from attrgraph.sources import bucket_of, read_edges

ROW_BYTES = 48
BROADCAST_BYTES = 64 << 20


@dataclass(frozen=True)
class Advice:
    frontier_rows: float
    broadcast: bool
    prune: bool


def advise(eps: float, alpha: float, seeds: int, buckets: int, beta: float = 2.0, mass: float = 1.0) -> Advice:
    """From the output bound beta * mass / ((1 - alpha) * eps) of each seed, before anything runs.

    The frontier is broadcast when its bound is under BROADCAST_BYTES; buckets are pruned when it can't touch most of them.
    """
    rows = seeds * beta * mass / ((1 - alpha) * eps)
    return Advice(rows, rows * ROW_BYTES <= BROADCAST_BYTES, rows < 4 * buckets)


def diffuse_pruned(spark: SparkSession, path: str, degrees: DataFrame, start: DataFrame, alpha: float = 0.8, eps: float = 1e-3, buckets: int = 64, rounds: int = 200) -> tuple[DataFrame, list[dict]]:
    """Threshold push over a layout of ``sources.write_edges``: each round reads the frontier's buckets alone.

    Returns the state (seed_id, node_id, deg, residual, reserve) and, for each round, rows in the frontier and buckets read.
    The frontier's buckets (at most ``buckets`` numbers) come to the driver; the frontier is broadcast only under a counted
    size. Mass on nodes without edges stays out, as in ``diffusion.diffuse``.
    """
    state = materialise(start.groupBy("seed_id", "node_id").agg(F.sum("mass").alias("residual")).join(degrees, "node_id").select("seed_id", "node_id", "deg", "residual", F.lit(0.0).alias("reserve")), "state")
    log: list[dict] = []
    hot = (F.col("residual") > 0) & (F.col("residual") >= eps * F.col("deg"))
    for _ in range(rounds):
        frontier = state.where(hot).select("seed_id", "node_id", "residual", bucket_of("node_id", buckets).alias("b"))
        touched = [(r.b, r.n) for r in frontier.groupBy("b").agg(F.count("*").alias("n")).collect()]
        if not touched:
            break
        rows = sum(n for _, n in touched)
        small = rows * ROW_BYTES <= BROADCAST_BYTES
        edges = read_edges(spark, path, [b for b, _ in touched] if len(touched) < buckets else None).edges
        front = frontier.drop("b").withColumnRenamed("node_id", "src")
        sent = edges.join(F.broadcast(front) if small else front, "src").select("seed_id", F.col("dst").alias("node_id"), F.col("dst_deg").alias("deg"), (alpha * F.col("residual") * F.col("w") / F.col("src_deg")).alias("residual"), F.lit(0.0).alias("reserve"))
        kept = state.select("seed_id", "node_id", "deg", F.when(hot, 0.0).otherwise(F.col("residual")).alias("residual"), (F.col("reserve") + F.when(hot, (1 - alpha) * F.col("residual")).otherwise(0.0)).alias("reserve"))
        after = materialise(kept.union(sent).groupBy("seed_id", "node_id").agg(F.max("deg").alias("deg"), F.sum("residual").alias("residual"), F.sum("reserve").alias("reserve")), "state")
        log.append({"frontier": rows, "buckets": len(touched), "broadcast": small})
        discard(state)
        state = after
    return state, log


def incidence_step(rows: DataFrame, incidence: DataFrame, sizes: DataFrame, alpha: float) -> DataFrame:
    """One spread over a co-occurrence graph that is never built: item -> key -> item over (k, i).

    ``rows``: (seed_id, i, m); ``sizes``: (i, d) with d the weighted degree (pairs counted with multiplicity). An item's own
    share comes back from each of its keys and is taken off, so this equals a spread over the weighted graph.
    """
    out = rows.join(sizes, "i").select("seed_id", "i", (alpha * F.col("m") / F.col("d")).alias("m"))
    by_key = out.join(incidence, "i").groupBy("seed_id", "k").agg(F.sum("m").alias("m"))
    back = by_key.join(incidence, "k").groupBy("seed_id", "i").agg(F.sum("m").alias("m"))
    keys = incidence.groupBy("i").agg(F.count("*").alias("c"))
    own = out.join(keys, "i").select("seed_id", "i", (-F.col("m") * F.col("c")).alias("m"))
    return back.union(own).groupBy("seed_id", "i").agg(F.sum("m").alias("m")).where("m > 1e-15")


def pruned_edges(g: Graph, frontier: DataFrame, limit_rows: int = 1_000_000) -> DataFrame:
    """Edges that start in (src) ``frontier``: a broadcast semi join under ``limit_rows``, else a shuffled one."""
    small = frontier.limit(limit_rows + 1).count() <= limit_rows
    keys = frontier.select("src").distinct()
    return g.edges.join(F.broadcast(keys) if small else keys, "src", "left_semi")
