"""Exact quantities, truncated where a geometric tail falls under a tolerance: the oracles of the approximate methods."""

from __future__ import annotations

from math import ceil, log

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from attrgraph.functions import hash_uniform, vec_dot
from attrgraph.operators import whole
from attrgraph.operators.diffusion import ALPHA, start_unit
from attrgraph.operators.graph import Graph
from attrgraph.session import materialise


def levels(alpha: float, tol: float) -> int:
    """Steps after which the tail alpha^L is under ``tol``."""
    return max(1, ceil(log(tol) / log(alpha)))


def _small(g: Graph) -> bool:
    from attrgraph.operators.ball import WHOLE_EDGES

    return g.written and g.size <= WHOLE_EDGES


def diffuse(g: Graph, start: DataFrame, alpha: float = ALPHA, tol: float = 1e-6, norm: str = "walk", steps: int | None = None, keep_every: int = 8) -> DataFrame:
    """(seed_id, node_id, score): sum over l of (1 - alpha) alpha^l start P^l.

    ``norm='sym'`` uses the symmetric matrix in P's place, ``norm='reverse'`` P's transpose (columns smoothed over the graph).

    Mass left out is at most ``tol`` of a seed's start (walk norm). A kept graph of at most ``ball.WHOLE_EDGES`` edges goes to the
    workers as a whole, which do all levels of a seed at once; on others a level is a job.
    """
    if _small(g):
        return whole.diffuse(g, start, alpha, steps if steps is not None else levels(alpha, tol), norm)
    share = F.col("w") / {"walk": F.col("src_deg"), "reverse": F.col("dst_deg"), "sym": F.sqrt(F.col("src_deg") * F.col("dst_deg"))}[norm]
    edges = g.edges.select(F.col("src").alias("node_id"), "dst", share.alias("p"))
    current = start.groupBy("seed_id", "node_id").agg(F.sum("mass").alias("m"))
    total = current.select("seed_id", "node_id", ((1 - alpha) * F.col("m")).alias("score"))
    for l in range(1, (steps if steps is not None else levels(alpha, tol)) + 1):  # noqa: E741
        current = current.join(edges, "node_id").groupBy("seed_id", F.col("dst").alias("node_id")).agg((F.lit(alpha) * F.sum(F.col("m") * F.col("p"))).alias("m"))
        current = materialise(current, "level")
        total = total.union(current.select("seed_id", "node_id", ((1 - alpha) * F.col("m")).alias("score")))
        if l % keep_every == 0:
            total = materialise(total.groupBy("seed_id", "node_id").agg(F.sum("score").alias("score")), "walk")
    return total.groupBy("seed_id", "node_id").agg(F.sum("score").alias("score"))


def walk_scores(g: Graph, seeds: DataFrame, alpha: float = ALPHA, tol: float = 1e-6, **options) -> DataFrame:
    return diffuse(g, start_unit(seeds.join(g.degrees.select(F.col("node_id").alias("seed_id")), "seed_id", "left_semi")), alpha, tol, **options)


def check_symmetry(g: Graph, seeds: DataFrame, alpha: float = ALPHA, tol: float = 1e-8) -> DataFrame:
    """(a, b, gap): for pairs of seeds, |pi(a, b) deg(a) - pi(b, a) deg(b)|, which is 0 up to the tail."""
    if _small(g):
        return whole.symmetry_gaps(g, seeds, alpha, levels(alpha, tol))
    pi = walk_scores(g, seeds, alpha, tol).join(seeds.select(F.col("seed_id").alias("node_id")), "node_id", "left_semi")
    pi = pi.join(g.degrees.select(F.col("node_id").alias("seed_id"), "deg"), "seed_id").select(F.col("seed_id").alias("a"), F.col("node_id").alias("b"), (F.col("score") * F.col("deg")).alias("v"))
    other = pi.select(F.col("b").alias("a"), F.col("a").alias("b"), F.col("v").alias("u"))
    return pi.join(other, ["a", "b"]).where("a < b").select("a", "b", F.abs(F.col("v") - F.col("u")).alias("gap"))


def through(pi: DataFrame, affinity: DataFrame) -> DataFrame:
    """(seed_id, node_id, m): walk scores times the affinity, which is pairs (i, j, s) or factor rows (node_id, z) with s = z_i . z_j.

    Of factor rows no pairs are made: m is a row's product with the seed's sum of score times row.
    """
    if "z" not in affinity.columns:
        return pi.join(affinity, pi.node_id == affinity.i).groupBy("seed_id", F.col("j").alias("node_id")).agg(F.sum(F.col("score") * F.col("s")).alias("m"))
    parts = pi.join(affinity, "node_id").select("seed_id", "score", F.posexplode("z").alias("place", "x")).groupBy("seed_id", "place").agg(F.sum(F.col("score") * F.col("x")).alias("v"))
    psi = parts.groupBy("seed_id").agg(F.transform(F.sort_array(F.collect_list(F.struct("place", "v"))), lambda p: p["v"]).alias("psi"))
    return affinity.crossJoin(psi).select("seed_id", "node_id", vec_dot("psi", "z").alias("m")).where("m != 0")


def two_sided(g: Graph, affinity: DataFrame, seeds: DataFrame, alpha: float = ALPHA, tol: float = 1e-8) -> DataFrame:
    """(seed_id, node_id, score): the double sum over both walks' ends; ``affinity`` as in ``through``.

    The inner sum, over the ends of every node's walk, is one diffusion by the transposed steps, so the walks of all nodes aren't listed.
    """
    weighted = through(walk_scores(g, seeds, alpha, tol), affinity).join(g.degrees.select("node_id"), "node_id", "left_semi")
    return diffuse(g, weighted.select("seed_id", "node_id", F.col("m").alias("mass")), alpha, tol, norm="reverse")


def two_sided_lifted(g: Graph, affinity: DataFrame, seeds: DataFrame, alpha: float = ALPHA, tol: float = 1e-8, steps: int | None = None) -> DataFrame:
    """The same through one forward diffusion of the lifted walk scores, divided by degree at the end."""
    lifted = through(walk_scores(g, seeds, alpha, tol, steps=steps), affinity)
    phi = materialise(lifted.join(g.degrees, "node_id").select("seed_id", "node_id", (F.col("m") * F.col("deg")).alias("mass")), "phi")
    rho = diffuse(g, phi, alpha, tol, steps=steps).join(g.degrees, "node_id")
    return rho.select("seed_id", "node_id", (F.col("score") / F.col("deg")).alias("score"))


#: Positions up to which a row is smoothed as one.
PACKED = 64


def _smoothed_rows(g: Graph, factors: DataFrame, alpha: float, steps: int, norm: str, width: int) -> DataFrame:
    """(node_id, h): as ``smoothed_embeddings``, an edge carries a row at once."""
    share = F.col("w") / {"walk": F.col("dst_deg"), "reverse": F.col("dst_deg"), "sym": F.sqrt(F.col("src_deg") * F.col("dst_deg"))}[norm]
    edges = g.edges.select(F.col("src").alias("node_id"), "dst", share.alias("p"))
    sums = lambda m: F.array(*[F.sum(m(i)) for i in range(width)])
    current = factors.where(F.exists("z", lambda x: x != 0)).groupBy("node_id").agg(sums(lambda i: F.col("z")[i]).alias("m"))
    total = current = materialise(current, "level")
    for _ in range(steps):
        current = current.join(edges, "node_id").groupBy(F.col("dst").alias("node_id")).agg(sums(lambda i: F.lit(alpha) * F.col("p") * F.col("m")[i]).alias("m"))
        current = materialise(current, "level")
        total = total.union(current)
    return total.groupBy("node_id").agg(sums(lambda i: (1 - alpha) * F.col("m")[i]).alias("h"))


def smoothed_embeddings(g: Graph, factors: DataFrame, alpha: float = ALPHA, steps: int = 20, norm: str = "walk") -> DataFrame:
    """(node_id, h): factor rows smoothed over the graph, sum over l of (1 - alpha) alpha^l P^l Z.

    Each position is one diffusion, all in one job keyed by position. On large graphs, rows of up to PACKED positions move whole.
    """
    width = len(factors.first().z)
    if width <= PACKED and not _small(g):
        return _smoothed_rows(g, factors, alpha, steps, norm, width)
    start = factors.select("node_id", F.posexplode("z").alias("seed_id", "mass")).where("mass != 0")
    rows = diffuse(g, start, alpha, steps=steps, norm="reverse" if norm == "walk" else norm)
    packed = rows.groupBy("node_id").agg(F.map_from_entries(F.collect_list(F.struct("seed_id", "score"))).alias("m"))
    return packed.select("node_id", F.transform(F.sequence(F.lit(0), F.lit(width - 1)), lambda i: F.coalesce(F.col("m")[i], F.lit(0.0))).alias("h"))


def denoise_objective(h: DataFrame, h0: DataFrame, g: Graph, alpha: float = ALPHA) -> DataFrame:
    """One row (fit, smooth, objective): (1 - alpha) ||H - H0||^2 + alpha trace(H^T L H), L the normalised Laplacian."""
    gap = F.aggregate(F.zip_with("h", "z", lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x)
    fit = h.join(h0, "node_id").agg(F.sum(gap).alias("fit"))
    size = h.agg(F.sum(vec_dot("h", "h")).alias("own"))
    left, right = h.select(F.col("node_id").alias("src"), F.col("h").alias("a")), h.select(F.col("node_id").alias("dst"), F.col("h").alias("b"))
    cross = g.edges.join(left, "src").join(right, "dst").agg(F.sum(F.col("w") * vec_dot("a", "b") / F.sqrt(F.col("src_deg") * F.col("dst_deg"))).alias("cross"))
    one = fit.join(F.broadcast(size)).join(F.broadcast(cross))  # single rows
    smooth = F.col("own") - F.coalesce("cross", F.lit(0.0))
    return one.select("fit", smooth.alias("smooth"), ((1 - alpha) * F.col("fit") + alpha * smooth).alias("objective"))


def knn_cluster(h: DataFrame, seeds: DataFrame, k: int) -> DataFrame:
    """(seed_id, node_id, score, rank): the k largest inner products of smoothed rows; ties to the smaller id."""
    mine = h.join(seeds.select(F.col("seed_id").alias("node_id")), "node_id", "left_semi").select(F.col("node_id").alias("seed_id"), F.col("h").alias("q"))
    rows = h.join(F.broadcast(mine)).select("seed_id", "node_id", vec_dot("q", "h").alias("score"))  # a stated batch of seeds
    order = Window.partitionBy("seed_id").orderBy(F.desc("score"), "node_id")
    return rows.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)


def walk_scores_mc(g: Graph, seeds: DataFrame, alpha: float = ALPHA, walks: int = 1000, seed: int = 1, most: int = 60) -> DataFrame:
    """(seed_id, node_id, score): share of ``walks`` sampled walks that stop at a node; picks are hashed, so a retry repeats them.

    Walks longer than ``most`` steps stop where they are (a share of alpha^most of them).
    """
    from attrgraph.operators.graph import adjacency

    packed = materialise(adjacency(g, 1 << 30).select(F.col("node_id").alias("at"), F.transform(F.sort_array("nb"), lambda x: x["dst"]).alias("nb")), "walks")
    live = seeds.select("seed_id", F.explode(F.sequence(F.lit(1), F.lit(walks))).alias("walk"), F.col("seed_id").alias("at"))
    stopped = None
    for step in range(most):
        go = hash_uniform(F.lit(seed), F.col("seed_id"), F.col("walk"), F.lit(step)) < alpha
        rows = live.withColumn("go", go if step < most - 1 else F.lit(False))
        done = rows.where("not go").groupBy("seed_id", F.col("at").alias("node_id")).agg(F.count("*").alias("n"))
        stopped = materialise(done if stopped is None else stopped.union(done).groupBy("seed_id", "node_id").agg(F.sum("n").alias("n")), "stops")
        pick = F.element_at("nb", (F.floor(hash_uniform(F.lit(seed + 1), F.col("seed_id"), F.col("walk"), F.lit(step)) * F.size("nb")) + 1).cast("int"))
        live = materialise(rows.where("go").join(packed, "at").select("seed_id", "walk", pick.alias("at")), "walks")
        if live.isEmpty():
            break
    return stopped.select("seed_id", "node_id", (F.col("n") / walks).alias("score"))
