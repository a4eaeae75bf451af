"""Experiments: many methods, seeds and settings in one job each."""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from attrgraph.functions import vec_norm
from attrgraph.operators import cluster, diffusion, measures
from attrgraph.operators.baselines import attrs as by_attrs
from attrgraph.operators.baselines import embed, flow, heat, links, push
from attrgraph.operators.graph import Graph
from attrgraph.session import materialise


@dataclass
class Bench:
    """A graph with unit attribute rows, labels, and the seeds to run."""

    g: Graph
    attrs: DataFrame
    truth: DataFrame
    seeds: DataFrame


PAIR_TABLE_NODES = 2000


def seeds_for(nodes: int) -> int:
    """How many seeds an experiment takes on a graph of that size."""
    return 25 if nodes < 1000 else 100 if nodes < 10_000 else 500


def methods(factors: DataFrame | None = None, factors_exp: DataFrame | None = None, eps: float = 1e-4, flow_share: float = 0.3, **options) -> dict[str, Callable[[Bench], DataFrame]]:
    """Scores (seed_id, node_id, score) by method name: all that score nodes of a seed without an embedding.

    The flows start with ``flow_share`` of the graph's volume; SimRank is exact up to PAIR_TABLE_NODES nodes, then sampled.
    """
    volume = lambda g: flow_share * g.degrees.agg(F.sum("deg")).first()[0]

    def weighted(b: Bench) -> DataFrame:
        g = push.attr_weighted_graph(b.g, b.attrs).kept()
        return flow.pnorm_flow(g, b.seeds, mass=volume(g), tol=1e-2)

    out: dict[str, Callable[[Bench], DataFrame]] = {
        "ppr_push": lambda b: push.seeded_pagerank(b.g, b.seeds, eps=eps),
        "ppr_attr_weighted": lambda b: push.attr_weighted_pagerank(b.g, b.attrs, b.seeds, eps=eps),
        "heat_kernel": lambda b: heat.heat_kernel(b.g, b.seeds, eps=eps),
        "capacity_release": lambda b: flow.capacity_release(b.g, b.seeds),
        "pnorm_flow": lambda b: flow.pnorm_flow(b.g, b.seeds, mass=volume(b.g), tol=1e-2),
        "weighted_flow": weighted,
        "jaccard": lambda b: links.jaccard(b.g, b.seeds),
        "adamic_adar": lambda b: links.adamic_adar(b.g, b.seeds),
        "common_neighbors": lambda b: links.common_neighbors(b.g, b.seeds),
        "simrank": lambda b: links.simrank(b.g, seeds=b.seeds) if b.g.degrees.count() <= PAIR_TABLE_NODES else links.simrank_mc(b.g, b.seeds),
        "attr_cosine": lambda b: by_attrs.similarity(b.attrs, b.seeds),
        "attr_expcos": lambda b: by_attrs.similarity(b.attrs, b.seeds, "expcos"),
        "attribute_pagerank": lambda b: by_attrs.attribute_pagerank(b.g, b.attrs).join(F.broadcast(b.seeds)).select("seed_id", "node_id", "score"),
        "aalc_topology": lambda b: cluster.local_affinity(b.g, None, b.seeds, eps=eps, **options),
    }
    if factors is not None:
        out["aalc_cosine"] = lambda b: cluster.local_affinity(b.g, factors, b.seeds, eps=eps, **options)
    if factors_exp is not None:
        out["aalc_exponential"] = lambda b: cluster.local_affinity(b.g, factors_exp, b.seeds, eps=eps, **options)
    return out


def embeddings(b: Bench, k: int = 16) -> dict[str, Callable[[], DataFrame]]:
    """(node_id, e) by name: the four embeddings, at small sizes."""
    return {
        "second_order_walks": lambda: embed.walk_embedding(b.g, 1.0, 0.5, length=10, walks=4, dim=k),
        "aggregation": lambda: embed.packed_rows(embed.neighbor_aggregate(b.g, b.attrs, dim=k)),
        "affinity_factorization": lambda: embed.affinity_factorization(b.g, b.attrs, k=k, steps=3, method="randomized"),
        "cross_fusion": lambda: embed.cross_fusion(b.g, b.attrs, k=k, rounds=1, steps=2),
    }


def extracted(b: Bench, e: DataFrame, groups: int, radius: float = 0.3) -> dict[str, DataFrame]:
    """Clusters of truth size out of an embedding, by K-NN, spectral and density grouping."""
    unit = materialise(e.select("node_id", F.transform("e", lambda v: v / F.greatest(vec_norm("e"), F.lit(1e-12))).alias("e")), "e")
    size = materialise(measures.truth_sizes(b.seeds, b.truth), "size")
    most = size.agg(F.max("size")).first()[0] or 1
    return {
        "knn": cluster.top(embed.cluster_knn(unit, b.seeds, most), size),
        "spectral": embed.group_of_seed(embed.cluster_spectral(unit, groups, steps=3), unit, b.seeds, size),
        "density": embed.group_of_seed(embed.cluster_density(unit, radius), unit, b.seeds, size),
    }


def clusters_of(b: Bench, chosen: dict[str, Callable[[Bench], DataFrame]], pad: str = "none") -> dict[str, DataFrame]:
    """Written clusters as large as the truth, for every method."""
    size = materialise(measures.truth_sizes(b.seeds, b.truth), "sizes")
    return {name: materialise(cluster.padded(cluster.top(run(b), size, b.seeds), size, b.g.degrees, pad), "clusters") for name, run in chosen.items()}


def quality(b: Bench, chosen: dict[str, Callable[[Bench], DataFrame]], pad: str = "none") -> DataFrame:
    """(method, seed_id, hits, size, truth_size) of every method's clusters."""
    rows = None
    for name, c in clusters_of(b, chosen, pad).items():
        part = measures.hits(c, b.truth).select(F.lit(name).alias("method"), "seed_id", "hits", "size", "truth_size")
        rows = part if rows is None else rows.union(part)
    return rows


def summary(rows: DataFrame) -> DataFrame:
    """(method, precision, recall, seeds) of ``quality``."""
    return rows.groupBy("method").agg(F.avg(F.col("hits") / F.col("size")).alias("precision"), F.avg(F.col("hits") / F.col("truth_size")).alias("recall"), F.count("*").alias("seeds"))


def cohesion(b: Bench, clusters: dict[str, DataFrame]) -> DataFrame:
    """(method, precision, recall, conductance, scatter, seeds): means over seeds of every method's clusters, of all methods in one job."""
    by, every = ("method", "seed_id"), None
    for name, c in clusters.items():
        part = c.select(F.lit(name).alias("method"), "seed_id", "node_id")
        every = part if every is None else every.union(part)
    every = materialise(every, "clusters")
    told = measures.hits(every, b.truth, by).join(measures.conductance(every, b.g, by), [*by]).join(measures.scatter(every, b.attrs, by), [*by], "left")
    means = [F.avg(F.col("hits") / F.col("size")).alias("precision"), F.avg(F.col("hits") / F.col("truth_size")).alias("recall"), F.avg("conductance").alias("conductance"), F.avg("scatter").alias("scatter")]
    return told.groupBy("method").agg(*means, F.count("*").alias("seeds"))


LADDER = [10.0**-i for i in range(9)]


def by_eps(b: Bench, levels: list[float], factors: DataFrame | None = None, factors_exp: DataFrame | None = None, pads: tuple[str, ...] = ("none", "id"), alpha: float = diffusion.ALPHA, sigma: float = 0.1) -> DataFrame:
    """(eps, method, pad, recall): every threshold and seed in one job for each method.

    A run is a (seed, level) pair: run ids stand in for seed ids, and eps is a column of the start. Methods: push PageRank, plain and on
    attribute-weighted edges, the heat kernel, and the pipeline without attributes and with each of the given factors.
    """
    spark = b.g.edges.sparkSession
    table = F.broadcast(spark.createDataFrame(list(enumerate(levels)), "level int, eps double"))
    n = len(levels)
    runs = materialise(b.seeds.join(table).select((F.col("seed_id") * n + F.col("level")).alias("run"), "seed_id", "eps"), "runs")
    g, weighted = b.g.kept(), push.attr_weighted_graph(b.g, b.attrs).kept()
    start = runs.select(F.col("run").alias("seed_id"), F.col("seed_id").alias("node_id"), F.lit(1.0).alias("mass"), "eps")
    size = measures.truth_sizes(b.seeds, b.truth).join(runs, "seed_id").select(F.col("run").alias("seed_id"), "size")
    size = materialise(size, "sizes")
    pi = materialise(diffusion.scores(diffusion.diffuse(g, start, alpha, "eps", "hybrid", sigma)), "pi")
    per_degree = lambda x: x.select("seed_id", "node_id", (F.col("score") / F.col("deg")).alias("score"))
    found = {name: per_degree(diffusion.scores(diffusion.diffuse(graph, start, alpha, "eps", "threshold", sigma))) for name, graph in (("ppr_push", g), ("ppr_attr_weighted", weighted))}
    found["heat_kernel"] = heat.heat_kernel(g, start, eps="eps")
    for name, z in (("aalc_topology", None), ("aalc_cosine", factors), ("aalc_exponential", factors_exp)):
        if name != "aalc_topology" and z is None:
            continue
        phi = cluster.lift_identity(pi) if z is None else cluster.lift(pi, cluster.seed_profile(pi, z), z, g)
        phi = phi.join(runs.select(F.col("run").alias("seed_id"), "eps"), "seed_id")
        found[name] = per_degree(diffusion.scores(diffusion.diffuse(g, materialise(phi, "phi"), alpha, "eps", "hybrid", sigma, relative_eps=True)))
    labels = materialise(b.truth.groupBy("node_id").agg(F.collect_set("label").alias("labels")), "labels")
    mine = runs.join(labels.select(F.col("node_id").alias("seed_id"), F.col("labels").alias("own")), "seed_id").select(F.col("run").alias("seed_id"), "own", "eps")
    own = runs.select(F.col("run").alias("seed_id"), F.col("seed_id").alias("node_id"), F.lit(0.0).alias("score"), F.lit(1).alias("rank"))
    out = None
    for name, scored in found.items():
        c = cluster.top(scored, size)
        c = materialise(c.union(own.join(c.select("seed_id", "node_id"), ["seed_id", "node_id"], "left_anti")), "clusters")
        for pad in pads:
            hit = cluster.padded(c, size, g.degrees, pad).join(labels, "node_id").join(mine, "seed_id").where(F.arrays_overlap("labels", "own")).groupBy("seed_id").agg(F.count("*").alias("hits"))
            part = mine.join(hit, "seed_id", "left").join(size, "seed_id").groupBy("eps").agg(F.avg(F.coalesce("hits", F.lit(0)) / F.col("size")).alias("recall")).select("eps", F.lit(name).alias("method"), F.lit(pad).alias("pad"), "recall")
            out = part if out is None else out.union(part)
    return out


def grid(b: Bench, params: list[dict], factors: Callable[[dict], DataFrame | None]) -> tuple[dict, list[tuple[dict, float]]]:
    """(best setting, all settings with their precision) of the pipeline's parameters, for precision at truth size.

    ``factors`` gives the factor rows of a setting; what it reads of a setting (k, delta, kernel) doesn't go to the pipeline.
    """
    seen = []
    for p in params:
        z = factors(p)
        options = {k: v for k, v in p.items() if k not in ("k", "delta", "kernel", "features")}
        rows = quality(b, {"x": lambda b, z=z, o=options: cluster.local_affinity(b.g, z, b.seeds, **o)})
        seen.append((p, summary(rows).first().precision))
    return max(seen, key=lambda x: x[1])[0], seen


def timed(run: Callable[[], DataFrame]) -> float:
    """Wall seconds of a frame written nowhere."""
    began = time.time()
    run().write.format("noop").mode("overwrite").save()
    return time.time() - began
