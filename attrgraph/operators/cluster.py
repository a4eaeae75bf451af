"""The three-step pipeline from seeds to clusters, and ways to cut a cluster out of scores."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from attrgraph.functions import vec_dot
from attrgraph.operators.diffusion import ALPHA, diffuse, scores, start_unit
from attrgraph.operators.graph import Graph, ranked_nodes
from attrgraph.session import materialise, written

#: Factor rows longer than this are summed place by place.
WIDE = 64


def seed_profile(pi: DataFrame, factors: DataFrame) -> DataFrame:
    """(seed_id, psi): factor rows of the nodes in (seed_id, node_id, score), summed by score.

    Sums are partial in each task before they move: k numbers a seed and task. Wide rows are summed by place, since a plan with
    a sum for each of a thousand places takes longer to compile than to run.
    """
    width = len(factors.first().z) if not factors.isEmpty() else 0
    joined = pi.join(factors, "node_id")
    if width > WIDE:
        sums = joined.select("seed_id", "score", F.posexplode("z").alias("place", "x")).groupBy("seed_id", "place").agg(F.sum(F.col("score") * F.col("x")).alias("s"))
        return sums.groupBy("seed_id").agg(F.transform(F.sort_array(F.collect_list(F.struct("place", "s"))), lambda r: r["s"]).alias("psi"))
    return joined.groupBy("seed_id").agg(F.array(*[F.sum(F.col("score") * F.col("z")[i]) for i in range(width)]).cast("array<double>").alias("psi"))


def lift(pi: DataFrame, psi: DataFrame, factors: DataFrame, g: Graph, scope: str = "explored") -> DataFrame:
    """(seed_id, node_id, mass): psi . z times degree, negative values clipped to 0.

    ``explored`` keeps the nodes of ``pi``, as a local method must; ``all`` scores every node of the factor table
    for each seed of the batch. The explored scope misses mass on nodes that the first diffusion didn't reach, so the error
    bound of the whole pipeline holds for ``all`` only.
    """
    if scope == "explored":
        rows = pi.select("seed_id", "node_id", "deg").join(factors, "node_id").join(psi, "seed_id")
    elif scope == "all":
        # psi is one row a seed: a stated batch of seeds against all rows
        rows = factors.join(g.degrees, "node_id").join(F.broadcast(psi))
    else:
        raise ValueError(f"no scope {scope}")
    return rows.select("seed_id", "node_id", F.greatest(vec_dot("psi", "z") * F.col("deg"), F.lit(0.0)).alias("mass")).where("mass > 0")


def lift_identity(pi: DataFrame) -> DataFrame:
    """The lift of a graph without attributes: score times degree."""
    return pi.select("seed_id", "node_id", (F.col("score") * F.col("deg")).alias("mass"))


def local_affinity(
    g: Graph, factors: DataFrame | None, seeds: DataFrame, alpha: float = ALPHA, eps: float = 1e-4, sigma: float = 0.1,
    strategy: str = "hybrid", scope: str = "explored", engine: str = "auto",
) -> DataFrame:
    """(seed_id, node_id, score): two-sided affinity of seeds with the nodes around them, for all seeds in one job.

    ``factors=None`` leaves attributes out. Rounds are bounded by eps and alpha, never by the graph. A kept graph and written
    factors are used as they are, so what they cost is paid once for all calls.
    """
    g = g.kept()
    options = {"alpha": alpha, "sigma": sigma, "strategy": strategy, "engine": engine}
    pi = materialise(scores(diffuse(g, start_unit(seeds), eps=eps, **options)), "pi")
    if factors is None:
        phi = lift_identity(pi)
    else:
        factors = written(factors, "factors")
        phi = lift(pi, materialise(seed_profile(pi, factors), "psi"), factors, g, scope)
    rho = scores(diffuse(g, materialise(phi, "phi"), eps=eps, relative_eps=True, **options))
    return rho.select("seed_id", "node_id", (F.col("score") / F.col("deg")).alias("score"))


def top(scored: DataFrame, size: DataFrame | int, seeds: DataFrame | None = None) -> DataFrame:
    """(seed_id, node_id, score, rank): the largest scores of each seed, ties to the smaller id.

    ``size`` is a number or (seed_id, size). With ``seeds`` the seed itself always takes a place (the first), also where
    it has no score.
    """
    rows = scored.select("seed_id", "node_id", "score", F.lit(0).alias("own"))
    if seeds is not None:
        own = seeds.select("seed_id", F.col("seed_id").alias("node_id"), F.lit(0.0).alias("score"), F.lit(1).alias("own"))
        rows = rows.union(own).groupBy("seed_id", "node_id").agg(F.max("score").alias("score"), F.max("own").alias("own"))
    order = Window.partitionBy("seed_id").orderBy(F.desc("own"), F.desc("score"), "node_id")
    ranked = rows.withColumn("rank", F.row_number().over(order))
    if isinstance(size, int):
        ranked = ranked.where(F.col("rank") <= size)
    else:
        ranked = ranked.join(size, "seed_id").where("rank <= size")
    return ranked.select("seed_id", "node_id", "score", "rank")


def padded(clusters: DataFrame, size: DataFrame, nodes: DataFrame, pad: str = "id", similarity: DataFrame | None = None) -> DataFrame:
    """Clusters filled up to (seed_id, size) with nodes they lack: smallest ids (``id``), or the largest of
    (seed_id, node_id, score) ``similarity`` (``attr``); ``none`` leaves them as they are."""
    if pad == "none":
        return clusters
    have = clusters.groupBy("seed_id").agg(F.count("*").alias("have"))
    lack = size.join(have, "seed_id", "left").select("seed_id", F.coalesce("have", F.lit(0)).alias("have"), (F.col("size") - F.coalesce("have", F.lit(0))).alias("lack")).where("lack > 0")
    if pad == "attr" and similarity is not None:
        spare = similarity.select("seed_id", "node_id", F.col("score").alias("s"))
    else:
        # what a seed lacks is among the first ``size`` nodes, which are met by their places
        places = lack.join(size, "seed_id").select("seed_id", F.explode(F.sequence(F.lit(1), F.col("size").cast("long"))).alias("place"))
        spare = places.join(ranked_nodes(nodes), "place").select("seed_id", "node_id", F.lit(0.0).alias("s"))
    spare = spare.join(clusters.select("seed_id", "node_id"), ["seed_id", "node_id"], "left_anti")
    order = Window.partitionBy("seed_id").orderBy(F.desc("s"), "node_id")
    more = spare.withColumn("r", F.row_number().over(order)).join(lack, "seed_id").where("r <= lack")
    return clusters.union(more.select("seed_id", "node_id", F.lit(0.0).alias("score"), (F.col("have") + F.col("r")).cast("int").alias("rank")))


def sweep_cut(scored: DataFrame, g: Graph, total_volume: float | None = None) -> DataFrame:
    """(seed_id, rank, node_id, score, volume, cut, conductance, best): every prefix of the order by score; ``best`` marks the
    prefix of least conductance (the shortest of equal ones)."""
    order = Window.partitionBy("seed_id").orderBy(F.desc("score"), "node_id")
    ranked = scored.select("seed_id", "node_id", "score").withColumn("rank", F.row_number().over(order)).join(g.degrees, "node_id")
    total = total_volume if total_volume is not None else g.degrees.agg(F.sum("deg")).first()[0]
    one = ranked.select("seed_id", F.col("node_id").alias("src"), F.col("rank").alias("ra"))
    two = ranked.select("seed_id", F.col("node_id").alias("dst"), F.col("rank").alias("rb"))
    inner = one.join(g.edges.select("src", "dst", "w"), "src").join(two, ["seed_id", "dst"]).where("ra > rb")
    inner = inner.groupBy("seed_id", F.col("ra").alias("rank")).agg(F.sum("w").alias("inside"))
    upto = Window.partitionBy("seed_id").orderBy("rank").rowsBetween(Window.unboundedPreceding, 0)
    rows = ranked.join(inner, ["seed_id", "rank"], "left").withColumn("volume", F.sum("deg").over(upto)).withColumn("cut", F.col("volume") - 2 * F.sum(F.coalesce("inside", F.lit(0.0))).over(upto))
    least = F.least(F.col("volume"), F.lit(float(total)) - F.col("volume"))
    rows = rows.withColumn("conductance", F.when(least > 0, F.col("cut") / least).otherwise(F.lit(1.0)))
    best = F.row_number().over(Window.partitionBy("seed_id").orderBy("conductance", "rank")) == 1
    return rows.select("seed_id", "rank", "node_id", "score", "volume", "cut", "conductance", best.alias("best"))
