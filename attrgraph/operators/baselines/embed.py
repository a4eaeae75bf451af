"""Node embeddings and the ways to cut a seed's cluster out of them."""

from __future__ import annotations

from collections.abc import Iterator
from functools import partial

import numpy as np
import pandas as pd
from pyspark.ml.clustering import KMeans
from pyspark.ml.feature import BucketedRandomProjectionLSH, Word2Vec
from pyspark.ml.functions import array_to_vector, vector_to_array
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from attrgraph.functions import gaussian_hash, hash_uniform, sq_distance, vec_dot, vec_norm
from attrgraph.operators import exact, factors
from attrgraph.operators.builders import vector_knn
from attrgraph.operators.graph import Graph, adjacency, connected, from_edges
from attrgraph.session import materialise, workers


def walk_embedding(g: Graph, p: float = 1.0, q: float = 1.0, length: int = 20, walks: int = 5, dim: int = 32, window: int = 5, seed: int = 1, iterations: int = 1) -> DataFrame:
    """(node_id, e): skip-gram vectors of second-order walks with return parameter p and in-out parameter q.

    A step draws among neighbours by rejection: a hashed candidate is taken with the share its weight has of the largest weight
    (1/p back, 1 to a neighbour of the last node, 1/q elsewhere); after three refusals the last candidate stands.
    """
    packed = materialise(adjacency(g, 1 << 30).select(F.col("node_id").alias("at"), F.transform(F.sort_array("nb"), lambda x: x["dst"]).alias("nb")), "walks")
    rows = g.degrees.select("node_id", F.explode(F.sequence(F.lit(1), F.lit(walks))).alias("walk")).select("node_id", "walk", F.lit(None).cast("long").alias("last"), F.col("node_id").alias("at"), F.array("node_id").alias("path"))
    most = max(1.0, 1 / p, 1 / q)
    for s in range(1, length):
        key = [F.lit(seed), F.col("node_id"), F.col("walk"), F.lit(s)]
        rows = rows.join(packed, "at")
        known = F.lit(None).cast("array<bigint>")
        if p != 1 or q != 1:
            rows = rows.join(packed.select(F.col("at").alias("last"), F.col("nb").alias("near")), "last", "left")
            known = F.col("near")
        weight = lambda c: F.when(c == F.col("last"), 1 / p).when(F.coalesce(F.array_contains(known, c), F.lit(True)), 1.0).otherwise(1 / q)  # noqa: B023, E731
        pick = None
        for attempt in (3, 2, 1):
            c = F.element_at("nb", (F.floor(hash_uniform(*key, F.lit(attempt)) * F.size("nb")) + 1).cast("int"))
            good = hash_uniform(*key, F.lit(attempt + 10)) * most < weight(c)
            pick = c if pick is None else F.when(good, c).otherwise(pick)
        rows = materialise(rows.select("node_id", "walk", F.col("at").alias("last"), pick.alias("at"), F.concat("path", F.array(pick)).alias("path")), "walks")
    sentences = rows.select(F.transform("path", lambda x: x.cast("string")).alias("words"))
    model = Word2Vec(vectorSize=dim, windowSize=window, minCount=0, seed=seed, maxIter=iterations, inputCol="words", outputCol="v").fit(sentences)
    return model.getVectors().select(F.col("word").cast("long").alias("node_id"), vector_to_array("vector").alias("e"))


def neighbor_aggregate(g: Graph, attrs: DataFrame, layers: int = 2, dim: int | None = None, seed: int = 1) -> DataFrame:
    """(node_id, pos, value): layers of own row beside the neighbours' mean, normalised.

    With ``dim=None`` a layer adds the two (identity weights); else both are projected by hashed normal weights to ``dim`` and
    passed through a rectifier.
    """
    rows = attrs.select("node_id", F.col("attr").cast("string").alias("pos"), "value")
    for layer in range(layers):
        near = g.edges.select(F.col("src").alias("node_id"), F.col("dst"), (F.col("w") / F.col("src_deg")).alias("p")).join(rows.withColumnRenamed("node_id", "dst"), "dst")
        mean = near.groupBy("node_id", "pos").agg(F.sum(F.col("p") * F.col("value")).alias("value"))
        if dim is None:
            both = rows.union(mean.select("node_id", "pos", "value")).groupBy("node_id", "pos").agg(F.sum("value").alias("value"))
        else:
            tagged = rows.select("node_id", F.concat(F.lit("o"), "pos").alias("pos"), "value").union(mean.select("node_id", F.concat(F.lit("m"), "pos").alias("pos"), "value"))
            wide = tagged.select("node_id", "pos", "value", F.explode(F.sequence(F.lit(0), F.lit(dim - 1))).alias("j"))
            both = wide.groupBy("node_id", F.col("j").cast("string").alias("pos")).agg(F.greatest(F.lit(0.0), F.sum(F.col("value") * gaussian_hash(F.lit(seed), F.lit(layer), F.col("pos"), F.col("j")))).alias("value"))
        norm = both.groupBy("node_id").agg(F.sqrt(F.sum(F.col("value") * F.col("value"))).alias("norm"))
        rows = both.join(norm, "node_id").select("node_id", "pos", F.when(F.col("norm") > 0, F.col("value") / F.col("norm")).otherwise(0.0).alias("value"))
        if layers > 1:
            rows = materialise(rows, "layer")
    return rows


def packed_rows(rows: DataFrame) -> DataFrame:
    """(node_id, e) of tall (node_id, pos, value); positions in alphabetic order, missing ones 0."""
    from attrgraph.operators.attributes import as_vectors

    return as_vectors(rows.withColumnRenamed("pos", "attr")).select("node_id", F.col("x").alias("e"))


def affinity_matrix(g: Graph, attrs: DataFrame, alpha: float = 0.5, steps: int = 6, direction: str = "forward") -> DataFrame:
    """(node_id, attr, value): ln(1 + n * walk affinity of a node with an attribute).

    ``forward`` smooths attribute columns that sum to 1 over nodes; ``backward`` smooths node rows that sum to 1 over attributes,
    scaled by the number of attributes. All attributes go in one diffusion.
    """
    if direction == "forward":
        total = attrs.groupBy("attr").agg(F.sum("value").alias("t"))
        start = attrs.join(total, "attr").select("node_id", "attr", (F.col("value") / F.col("t")).alias("mass"))
        scale = g.degrees.count()
    else:
        total = attrs.groupBy("node_id").agg(F.sum("value").alias("t"))
        start = attrs.join(total, "node_id").select("node_id", "attr", (F.col("value") / F.col("t")).alias("mass"))
        scale = attrs.select("attr").distinct().count()
    rows = exact.diffuse(g, start.where("mass > 0").select(F.col("attr").alias("seed_id"), "node_id", "mass"), alpha, steps=steps, norm="reverse")
    return rows.select("node_id", F.col("seed_id").alias("attr"), F.log1p(F.col("score") * scale).alias("value"))


def affinity_factorization(g: Graph, attrs: DataFrame, alpha: float = 0.5, k: int = 32, steps: int = 6, method: str = "auto") -> DataFrame:
    """(node_id, e): both affinity matrices reduced to k / 2 columns each, side by side."""
    halves = []
    for direction in ("forward", "backward"):
        m = materialise(affinity_matrix(g, attrs, alpha, steps, direction), "affinity")
        basis, _ = factors.truncated_svd(m, k // 2, method)
        halves.append(factors.project(m, basis))
    return halves[0].join(halves[1].select("node_id", F.col("y").alias("b")), "node_id").select("node_id", F.concat("y", "b").alias("e"))


def cross_fusion(g: Graph, attrs: DataFrame, k: int = 32, rounds: int = 2, neighbours: int = 10, alpha: float = 0.5, steps: int = 4) -> DataFrame:
    """(node_id, e): a topology view and an attribute view, each smoothed over the other's graph, joined and reduced.

    The attribute graph joins each node with its nearest by cosine of the reduced rows. Only the name of this method is public
    to us, so the details are our reading.
    """
    basis, _ = factors.truncated_svd(attrs, k, "auto")
    # nodes of the same attributes get the same row, to the last bit
    sets = attrs.groupBy("node_id").agg(F.sort_array(F.collect_list(F.struct("attr", "value"))).alias("set"))
    sets = materialise(sets.groupBy("set").agg(F.collect_list("node_id").alias("members")).select(F.array_min("members").alias("node_id"), "set", "members"), "sets")
    y = factors.project(sets.select("node_id", F.explode("set").alias("s")).select("node_id", "s.*"), basis)
    x = materialise(sets.select("node_id", "members").join(y, "node_id").select(F.explode("members").alias("node_id"), F.col("y").alias("e")), "view")
    unit = x.select("node_id", F.transform("e", lambda v: v / F.greatest(vec_norm("e"), F.lit(1e-12))).alias("x"))
    knn = vector_knn(unit, neighbours).select(F.col("q").alias("a"), F.col("other").alias("b"))
    own = from_edges(knn).kept()
    g = g.kept()
    hashed = g.degrees.select("node_id", F.array(*[gaussian_hash(F.lit(9), F.col("node_id"), F.lit(j)) for j in range(k)]).alias("e"))
    topology = materialise(_smooth(g, hashed, alpha, steps), "view")
    for _ in range(rounds):
        topology, x = materialise(_smooth(own, topology, alpha, steps), "view"), materialise(_smooth(g, x, alpha, steps), "view")
    both = x.join(topology.select("node_id", F.col("e").alias("t")), "node_id").select("node_id", F.posexplode(F.concat("e", "t")).alias("attr", "value")).select("node_id", F.col("attr").cast("string").alias("attr"), "value")
    reduced, _ = factors.truncated_svd(both, k)
    return factors.project(both, reduced).select("node_id", F.col("y").alias("e"))


def _smooth(g: Graph, rows: DataFrame, alpha: float, steps: int) -> DataFrame:
    out = exact.smoothed_embeddings(g, rows.select("node_id", F.col("e").alias("z")), alpha, steps, norm="sym")
    # nodes outside the graph keep their rows
    return rows.join(out, "node_id", "left").select("node_id", F.coalesce("h", "e").alias("e"))


def cluster_knn(rows: DataFrame, seeds: DataFrame, k: int, metric: str = "dot", lsh_buckets: int | None = None) -> DataFrame:
    """(seed_id, node_id, score, rank): nearest rows (node_id, e) by ``dot``, ``cosine`` or ``euclid`` (negative distance).

    ``lsh_buckets`` tables of random projections choose the candidates (euclid, approximate); else a stated batch of seeds is
    compared with all rows.
    """
    mine = rows.join(seeds.select(F.col("seed_id").alias("node_id")), "node_id", "left_semi").select(F.col("node_id").alias("seed_id"), F.col("e").alias("q"))
    if lsh_buckets:
        ready = rows.select("node_id", array_to_vector("e").alias("v"))
        model = BucketedRandomProjectionLSH(inputCol="v", outputCol="hashes", bucketLength=1.0, numHashTables=lsh_buckets, seed=1).fit(ready)
        wanted = mine.select("seed_id", array_to_vector("q").alias("v"))
        both = model.approxSimilarityJoin(wanted, ready, float("inf"), "d").select(F.col("datasetA.seed_id").alias("seed_id"), F.col("datasetB.node_id").alias("node_id"), (-F.col("d")).alias("score"))
    else:
        score = {"dot": vec_dot("q", "e"), "cosine": vec_dot("q", "e") / F.greatest(vec_norm("q") * vec_norm("e"), F.lit(1e-300)), "euclid": -F.sqrt(sq_distance("q", "e"))}[metric]
        both = rows.join(F.broadcast(mine)).select("seed_id", "node_id", score.alias("score"))
    order = Window.partitionBy("seed_id").orderBy(F.desc("score"), "node_id")
    return both.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)


def group_of_seed(groups: DataFrame, rows: DataFrame, seeds: DataFrame, size: DataFrame) -> DataFrame:
    """Clusters of the seed's group (node_id, group), nearest first, cut to (seed_id, size)."""
    own = seeds.join(groups.select(F.col("node_id").alias("seed_id"), "group"), "seed_id").join(rows.select(F.col("node_id").alias("seed_id"), F.col("e").alias("q")), "seed_id")
    both = groups.join(own, "group").join(rows, "node_id").select("seed_id", "node_id", (-F.sqrt(sq_distance("q", "e"))).alias("score"))
    order = Window.partitionBy("seed_id").orderBy(F.desc("score"), "node_id")
    return both.withColumn("rank", F.row_number().over(order)).join(size, "seed_id").where("rank <= size").select("seed_id", "node_id", "score", "rank")


def cluster_spectral(rows: DataFrame, n_clusters: int, neighbours: int = 10, dim: int = 8, steps: int = 10, seed: int = 1) -> DataFrame:
    """(node_id, group): K-means of rows smoothed over their nearest-neighbour graph (power iteration of a few hashed vectors)."""
    knn = vector_knn(rows.select("node_id", F.transform("e", lambda v: v / F.greatest(vec_norm("e"), F.lit(1e-12))).alias("x")), neighbours)
    g = from_edges(knn.select(F.col("q").alias("a"), F.col("other").alias("b"))).kept()
    start = rows.select("node_id", F.array(*[gaussian_hash(F.lit(seed), F.col("node_id"), F.lit(j)) for j in range(dim)]).alias("e"))
    out = _smooth(g, start, 0.95, steps)
    ready = out.select("node_id", array_to_vector(F.transform("e", lambda v: v / F.greatest(vec_norm("e"), F.lit(1e-12)))).alias("features"))
    model = KMeans(k=n_clusters, seed=seed, maxIter=20).fit(ready)
    return model.transform(ready).select("node_id", F.col("prediction").alias("group"))


def _within(frames: Iterator[pd.DataFrame], ids: np.ndarray, vectors: np.ndarray, radius: float) -> Iterator[pd.DataFrame]:
    for pdf in frames:
        if not len(pdf):
            continue
        mine, v = pdf["node_id"].to_numpy(), np.stack(pdf["e"].to_numpy())
        d = (v * v).sum(1)[:, None] - 2 * v @ vectors.T + (vectors * vectors).sum(1)[None]
        i, j = np.nonzero(d <= radius * radius + 1e-12)
        yield pd.DataFrame({"a": mine[i], "b": ids[j]})


def cluster_density(rows: DataFrame, radius: float, min_pts: int = 4, block: int = 2048) -> DataFrame:
    """(node_id, group): density clusters by connected core points; border points join their smallest core group; the rest
    are their own group (negative, -1 - id).

    Pairs within the radius come from all rows in blocks against all rows; cores are joined by connected components.
    """
    workers(rows.sparkSession)
    rows = materialise(rows.select("node_id", F.col("e").cast("array<double>").alias("e")), "rows")
    pieces = max(1, -(-rows.count() // block))
    near = None
    for b in range(pieces):
        some = rows.where(F.pmod(F.xxhash64("node_id"), F.lit(pieces)) == b).toPandas()
        if len(some):
            part = rows.mapInPandas(partial(_within, ids=some["node_id"].to_numpy(), vectors=np.stack(some["e"].to_numpy()), radius=radius), "a long, b long")
            near = part if near is None else near.union(part)
    near = materialise(near, "near")
    core = materialise(near.groupBy(F.col("a").alias("node_id")).agg(F.count("*").alias("n")).where(F.col("n") >= min_pts).select("node_id"), "core")
    inner = near.join(core.select(F.col("node_id").alias("a")), "a", "left_semi").join(core.select(F.col("node_id").alias("b")), "b", "left_semi")
    linked = connected(from_edges(inner)) if not inner.where("a != b").isEmpty() else core.select("node_id", F.col("node_id").alias("component_id")).limit(0)
    groups = core.join(linked, "node_id", "left").select("node_id", F.coalesce("component_id", "node_id").alias("group"))
    border = near.join(groups.select(F.col("node_id").alias("b"), "group"), "b").groupBy(F.col("a").alias("node_id")).agg(F.min("group").alias("g2"))
    return rows.select("node_id").join(groups, "node_id", "left").join(border, "node_id", "left").select("node_id", F.coalesce("group", "g2", -1 - F.col("node_id")).alias("group"))
