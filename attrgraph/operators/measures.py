"""Cost and accuracy measures of clusters, diffusions and factors."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from attrgraph.operators import factors
from attrgraph.operators.graph import BROADCAST_BYTES, ROW_BYTES, Graph
from attrgraph.operators.sharing import SharedGraph


def truth_sizes(seeds: DataFrame, truth: DataFrame) -> DataFrame:
    """(seed_id, size): number of nodes that share a label with the seed (several labels: their union)."""
    return _truth_members(seeds, truth).groupBy("seed_id").agg(F.count("*").alias("size"))


def _truth_members(seeds: DataFrame, truth: DataFrame) -> DataFrame:
    mine = seeds.join(truth.select(F.col("node_id").alias("seed_id"), "label"), "seed_id")
    return mine.join(truth, "label").select("seed_id", "node_id").distinct()


def hits(clusters: DataFrame, truth: DataFrame, by: tuple[str, ...] = ("seed_id",)) -> DataFrame:
    """(by, hits, size, truth_size) without listing any truth cluster: labels are compared where clusters are. ``by`` names what parts
    the clusters, the seed among it."""
    by = list(by)
    labels = truth.groupBy("node_id").agg(F.collect_set("label").alias("labels"))
    seeds = clusters.select(*by).distinct()
    mine = seeds.join(labels.select(F.col("node_id").alias("seed_id"), F.col("labels").alias("own")), "seed_id")
    both = clusters.join(mine, by).join(labels, "node_id", "left")
    found = both.groupBy(*by).agg(F.sum(F.coalesce(F.arrays_overlap("labels", "own"), F.lit(False)).cast("long")).alias("hits"), F.count("*").alias("size"))
    counts = labels.groupBy("labels").agg(F.count("*").alias("n"))  # one row for each set of labels
    if counts.count() * ROW_BYTES <= BROADCAST_BYTES:
        sizes = mine.select(*by, "own").join(F.broadcast(counts), F.arrays_overlap("own", "labels")).groupBy(*by).agg(F.sum("n").alias("truth_size"))
    else:
        sizes = seeds.join(truth_sizes(seeds.select("seed_id").distinct(), truth).withColumnRenamed("size", "truth_size"), "seed_id")
    return found.join(sizes, by)


def precision(clusters: DataFrame, truth: DataFrame) -> DataFrame:
    """One row: mean over seeds of hits / cluster size."""
    return hits(clusters, truth).agg(F.avg(F.col("hits") / F.col("size")).alias("precision"), F.count("*").alias("seeds"))


def recall(clusters: DataFrame, truth: DataFrame) -> DataFrame:
    """One row: mean over seeds of hits / truth size."""
    return hits(clusters, truth).agg(F.avg(F.col("hits") / F.col("truth_size")).alias("recall"), F.count("*").alias("seeds"))


def mean_rank(results: DataFrame) -> DataFrame:
    """(method, mean_rank) of (dataset, method, value): ties share the best rank, missing datasets are skipped."""
    w = Window.partitionBy("dataset").orderBy(F.desc("value"))
    return results.where("value is not null").withColumn("r", F.rank().over(w)).groupBy("method").agg(F.avg("r").alias("mean_rank"))


def conductance(clusters: DataFrame, g: Graph, by: tuple[str, ...] = ("seed_id",)) -> DataFrame:
    """(by, volume, cut, conductance): weight of edges that leave over the smaller of both sides' volumes."""
    by = list(by)
    members = clusters.select(*by, "node_id").distinct()
    total = g.degrees.agg(F.sum("deg")).first()[0] or 0.0
    vol = members.join(g.degrees, "node_id").groupBy(*by).agg(F.sum("deg").alias("volume"))
    if isinstance(g, SharedGraph):
        inner = g.inside(members, tuple(by))
    else:
        inner = members.withColumnRenamed("node_id", "src").join(g.edges.select("src", "dst", "w"), "src").join(members.withColumnRenamed("node_id", "dst"), [*by, "dst"], "left_semi")
        inner = inner.groupBy(*by).agg(F.sum("w").alias("inside"))
    rows = vol.join(inner, by, "left").withColumn("cut", F.col("volume") - F.coalesce("inside", F.lit(0.0)))
    least = F.least(F.col("volume"), F.lit(float(total)) - F.col("volume"))
    return rows.select(*by, "volume", "cut", F.when(least > 0, F.col("cut") / least).otherwise(F.lit(1.0)).alias("conductance"))


def truth_conductance(g: Graph, truth: DataFrame) -> DataFrame:
    """(label, volume, cut, conductance) of each label's nodes."""
    total = g.degrees.agg(F.sum("deg")).first()[0] or 0.0
    one, two = (truth.select(F.col("node_id").alias(k), F.col("label").alias(f"l_{k}")) for k in ("src", "dst"))
    rows = g.edges.join(one, "src").join(two, "dst", "left")
    agg = rows.groupBy(F.col("l_src").alias("label")).agg(F.sum("w").alias("volume"), F.sum(F.when(F.col("l_dst").eqNullSafe(F.col("l_src")), 0.0).otherwise(F.col("w"))).alias("cut"))
    least = F.least(F.col("volume"), F.lit(float(total)) - F.col("volume"))
    return agg.select("label", "volume", "cut", F.when(least > 0, F.col("cut") / least).otherwise(F.lit(1.0)).alias("conductance"))


def _common(one: str, other: str, names: list) -> Column:
    """Sum over the names, None left out, of the product of two arrays of counts."""
    return sum((F.col(one)[j] * F.col(other)[j] for j in range(len(names) - 1)), F.lit(0).cast("long"))


def counted_homophily(counts: DataFrame, names: list) -> DataFrame:
    """``graph.homophily`` from ``sharing.link_counts``: pairs of labelled ends, a null label like no other."""
    total = lambda c: F.aggregate(c, F.lit(0).cast("long"), lambda x, y: x + y)
    told = counts.agg(F.coalesce(F.sum(_common("own", "near", names)), F.lit(0)).alias("same"), F.coalesce(F.sum(total("own") * total("near")), F.lit(0)).alias("all"))
    return told.select(F.when(F.col("all") > 0, F.col("same") / F.col("all")).alias("homophily"), F.expr("`all` div 2").alias("labelled_edges"))


def counted_conductance(counts: DataFrame, names: list) -> DataFrame:
    """``truth_conductance`` from ``sharing.link_counts``."""
    total = counts.agg(F.sum("links")).first()[0] or 0
    sides = F.array(*[F.struct(F.lit(n).alias("label"), (F.col("own")[j] * F.col("links")).alias("volume"), (F.col("own")[j] * F.col("near")[j]).alias("inside")) for j, n in enumerate(names[:-1])])
    agg = counts.select(F.explode(sides).alias("s")).select("s.*").where("volume > 0").groupBy("label").agg(F.sum("volume").cast("double").alias("volume"), F.sum(F.col("volume") - F.col("inside")).cast("double").alias("cut"))
    least = F.least(F.col("volume"), F.lit(float(total)) - F.col("volume"))
    return agg.select("label", "volume", "cut", F.when(least > 0, F.col("cut") / least).otherwise(F.lit(1.0)).alias("conductance"))


def scatter(clusters: DataFrame, attrs: DataFrame, by: tuple[str, ...] = ("seed_id",)) -> DataFrame:
    """(by, scatter): mean squared distance of members' attribute rows to their mean."""
    by = list(by)
    size = clusters.groupBy(*by).agg(F.count("*").alias("c"))
    per = clusters.select(*by, "node_id").join(attrs, "node_id").groupBy(*by, "attr").agg(F.sum("value").alias("s"), F.sum(F.col("value") * F.col("value")).alias("q"))
    return per.join(size, by).groupBy(*by).agg(F.sum(F.col("q") / F.col("c") - (F.col("s") / F.col("c")) * (F.col("s") / F.col("c"))).alias("scatter"))


def zero_similarity(clusters: DataFrame, attrs: DataFrame) -> DataFrame:
    """(seed_id, members, zeros): other members whose attribute rows share nothing with the seed's."""
    mine = attrs.select(F.col("node_id").alias("seed_id"), "attr", F.col("value").alias("sv"))
    others = clusters.where("seed_id != node_id").select("seed_id", "node_id")
    dot = others.join(attrs, "node_id").join(mine, ["seed_id", "attr"]).groupBy("seed_id", "node_id").agg(F.sum(F.col("value") * F.col("sv")).alias("dot"))
    return others.join(dot, ["seed_id", "node_id"], "left").groupBy("seed_id").agg(F.count("*").alias("members"), F.sum((F.coalesce("dot", F.lit(0.0)) == 0).cast("long")).alias("zeros"))


def mean_degree(state: DataFrame, g: Graph) -> DataFrame:
    """One row: mean over seeds of the mean degree of nodes with reserve, beside the graph's."""
    own = state.where("reserve > 0").groupBy("seed_id").agg(F.avg("deg").alias("d"))
    return own.agg(F.avg("d").alias("cluster_degree")).join(F.broadcast(g.degrees.agg(F.avg("deg").alias("graph_degree"))))


def feature_bias(rows: DataFrame, deltas: tuple[float, ...] = (1.0, 2.0), draws: int = 100) -> list[tuple[float, str, float, float]]:
    """(delta, kind, mean ratio of estimated to true kernel over pairs and draws, mean over pairs of its deviation over draws).

    Rows (node_id, x) that are equal count as often as they occur: what comes to the driver grows with the distinct rows.
    """
    held = rows.groupBy("x").agg(F.count("*").alias("n")).collect()
    x, n = np.stack([np.array(r.x) for r in held]), np.array([float(r.n) for r in held])
    share, true, out = np.outer(n, n) / n.sum() ** 2, x @ x.T, []
    for delta in deltas:
        for kind in ("orthogonal", "iid"):
            mean, squares = np.zeros_like(true), np.zeros_like(true)
            for s in range(draws):
                y = factors.random_features(x, factors.frequencies(x.shape[1], delta, s, kind), delta)
                ratio = y @ y.T / np.exp(true / delta)
                gap = ratio - mean
                mean += gap / (s + 1)
                squares += gap * (ratio - mean)
            out.append((delta, kind, float((share * mean).sum()), float((share * np.sqrt(squares / draws)).sum())))
    return out


def diffusion_error(approx: DataFrame, exact: DataFrame, g: Graph) -> DataFrame:
    """(seed_id, least, most, node_id): smallest and largest (exact - approx) / degree, and where the largest is."""
    both = approx.select("seed_id", "node_id", F.col("reserve").alias("a")).join(exact.select("seed_id", "node_id", F.col("score").alias("e")), ["seed_id", "node_id"], "full").join(g.degrees, "node_id")
    gap = (F.coalesce("e", F.lit(0.0)) - F.coalesce("a", F.lit(0.0))) / F.col("deg")
    return both.withColumn("gap", gap).groupBy("seed_id").agg(F.min("gap").alias("least"), F.max("gap").alias("most"), F.max_by("node_id", F.struct("gap", -F.col("node_id"))).alias("node_id"))


def affinity_error(approx: DataFrame, exact: DataFrame) -> DataFrame:
    """(seed_id, least, most): range of exact - approximate two-sided affinity."""
    both = approx.select("seed_id", "node_id", F.col("score").alias("a")).join(exact.select("seed_id", "node_id", F.col("score").alias("e")), ["seed_id", "node_id"], "full")
    gap = F.coalesce("e", F.lit(0.0)) - F.coalesce("a", F.lit(0.0))
    return both.groupBy("seed_id").agg(F.min(gap).alias("least"), F.max(gap).alias("most"))


def affinity_bound(g: Graph, affinity: DataFrame, eps: float) -> DataFrame:
    """One row: (1 + sum of degree times a node's largest affinity) * eps, the error bound of the all-node lift."""
    top = affinity.groupBy(F.col("i").alias("node_id")).agg(F.max("s").alias("s")).join(g.degrees, "node_id")
    return top.agg(((1 + F.sum(F.col("deg") * F.col("s"))) * eps).alias("bound"))


def gram_error(attrs: DataFrame, basis: DataFrame, k: int) -> tuple[float, float]:
    """(spectral error of the projected Gram matrix, square of singular value k + 1), by the attribute-side Gram."""
    from attrgraph.operators.factors import gram

    names, g = gram(attrs)
    rows = {r.attr: r.v for r in basis.collect()}
    v = np.array([rows[n] for n in names])
    w, u = np.linalg.eigh(g)
    root = u * np.sqrt(np.maximum(w, 0))  # X = Q root^T with orthonormal Q
    left = root - v @ (v.T @ root)
    values = np.sort(w)[::-1]
    return float(np.linalg.norm(left.T @ left, 2)), float(max(values[k], 0)) if k < len(values) else 0.0


def speedup(times: DataFrame, ours: list[str]) -> DataFrame:
    """(dataset, method, ratio): a competitor's seconds over the mean of ours, of (dataset, method, seconds)."""
    mean = times.where(F.col("method").isin(ours)).groupBy("dataset").agg(F.avg("seconds").alias("own"))
    return times.where(~F.col("method").isin(ours)).join(mean, "dataset").select("dataset", "method", (F.col("seconds") / F.col("own")).alias("ratio"))
