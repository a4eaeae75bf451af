"""Undirected graphs as edge tables with degrees, and what is read off them."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from attrgraph.session import discard, fresh_path, materialise

EDGE_COLUMNS = ["src", "dst", "w", "src_deg", "dst_deg"]
#: What may be broadcast, by counted rows and the bytes that each takes.
BROADCAST_BYTES, ROW_BYTES = 64 << 20, 48
EDGES_PER_BUCKET, LEAST_BUCKETS, MOST_BUCKETS = 4_000_000, 16, 4096


@dataclass
class Packed:
    """A written adjacency, (node_id, chunk, nb) by bucket of the node, so that a frontier's reads touch its buckets alone.

    ``log`` has a row for each read: nodes asked for, buckets read, whether the nodes were broadcast.
    """

    rows: DataFrame
    buckets: int
    log: list[dict] = field(default_factory=list)

    def of(self, nodes: DataFrame) -> DataFrame:
        """Adjacency rows of the distinct ``nodes`` (node_id), which should be written: they are counted by bucket first."""
        keyed = nodes.select("node_id", _bucket("node_id", self.buckets).alias("bucket"))
        touched = [(r.bucket, r.n) for r in keyed.groupBy("bucket").agg(F.count("*").alias("n")).collect()]
        n = sum(c for _, c in touched)
        small = n * ROW_BYTES <= BROADCAST_BYTES
        self.log.append({"nodes": n, "buckets": len(touched), "broadcast": small})
        rows = self.rows.where(F.col("bucket").isin(sorted(b for b, _ in touched))) if len(touched) < self.buckets else self.rows
        keys = nodes.select("node_id")
        return rows.join(F.broadcast(keys) if small else keys, "node_id", "left_semi")


def _bucket(node: str, buckets: int):
    return F.pmod(F.xxhash64(node), F.lit(buckets)).cast("int")


@dataclass
class Graph:
    """edges(src, dst, w, src_deg, dst_deg), both directions of each undirected edge.

    A ``kept`` graph is written: its edges at once, degrees and packed adjacency when first asked for. All callers share them.
    With ``whole``, diffusions and heat kernels get a small graph (``ball.WHOLE_EDGES``) at once, where many runs on it follow.
    """

    edges: DataFrame
    written: bool = False
    whole: bool = False
    _parts: dict = field(default_factory=dict, repr=False, compare=False)

    @property
    def degrees(self) -> DataFrame:
        if "degrees" not in self._parts:
            rows = self.edges.groupBy(F.col("src").alias("node_id")).agg(F.max("src_deg").alias("deg"))
            if not self.written:
                return rows
            self._parts["degrees"] = materialise(rows, "degrees")
        return self._parts["degrees"]

    @property
    def packed(self) -> Packed:
        """The written adjacency of a kept graph."""
        if "packed" not in self._parts:
            if not self.written:
                raise ValueError("keep the graph first")
            spark = self.edges.sparkSession
            buckets = min(MOST_BUCKETS, max(LEAST_BUCKETS, self.size // EDGES_PER_BUCKET))
            path = fresh_path(spark, "adjacency")
            rows = adjacency(self).withColumn("bucket", _bucket("node_id", buckets))
            rows.repartition(buckets, "bucket").sortWithinPartitions("node_id").write.partitionBy("bucket").parquet(path)
            self._parts["packed"] = Packed(spark.read.schema(rows.schema).parquet(path), buckets)
        return self._parts["packed"]

    @property
    def size(self) -> int:
        """Directed edges."""
        if "size" not in self._parts:
            self._parts["size"] = self.edges.count()
        return self._parts["size"]

    def kept(self, label: str = "graph") -> Graph:
        """The same graph with its edges written to the shared folder once; a kept one is itself."""
        return self if self.written else Graph(materialise(self.edges, label), True, self.whole)


def from_edges(pairs: DataFrame, src: str = "a", dst: str = "b", weight: str | None = None, min_degree: int = 1) -> Graph:
    """A simple undirected graph of listed pairs.

    Loops and pairs with a null end go, both directions are made, repeated pairs count once (their largest weight).
    Weights must be positive. ``min_degree`` drops nodes of fewer neighbours, once.
    """
    w = F.col(weight).cast("double") if weight else F.lit(1.0)
    ends = pairs.where(F.col(src).isNotNull() & F.col(dst).isNotNull() & (F.col(src) != F.col(dst)))
    one = ends.select(F.least(src, dst).alias("a"), F.greatest(src, dst).alias("b"), w.alias("w")).where("w > 0")
    one = one.groupBy("a", "b").agg(F.max("w").alias("w"))
    # one exchange for both directions: a row turns into two
    both = one.select(F.explode(F.array(F.struct(F.col("a").alias("src"), F.col("b").alias("dst"), "w"), F.struct(F.col("b").alias("src"), F.col("a").alias("dst"), "w"))).alias("e")).select("e.*")
    if min_degree > 1:
        enough = both.groupBy("src").agg(F.count("*").alias("n")).where(F.col("n") >= min_degree).select("src")
        both = both.join(enough, "src", "left_semi").join(enough.select(F.col("src").alias("dst")), "dst", "left_semi")
    degree = both.groupBy("src").agg(F.sum("w").alias("src_deg"))
    edges = both.join(degree, "src").join(degree.select(F.col("src").alias("dst"), F.col("src_deg").alias("dst_deg")), "dst")
    return Graph(edges.select(*EDGE_COLUMNS))


def adjacency(g: Graph, chunk_size: int = 100_000) -> DataFrame:
    """(node_id, chunk, nb): neighbours packed in arrays of at most about ``chunk_size``, so a hub is many rows."""
    share = F.col("w") / F.col("src_deg")
    rows = g.edges.withColumn("chunk", F.pmod(F.xxhash64("dst"), F.ceil(F.col("src_deg") / chunk_size)).cast("int"))
    return rows.groupBy(F.col("src").alias("node_id"), "chunk").agg(F.collect_list(F.struct("dst", share.alias("p"), F.col("dst_deg").alias("deg"))).alias("nb"))


def volume(g: Graph, members: DataFrame, by: str = "seed_id") -> DataFrame:
    """Sum of degrees and number of the nodes in (seed_id, node_id)."""
    return members.join(g.degrees, "node_id").groupBy(by).agg(F.sum("deg").alias("volume"), F.count("*").alias("support"))


def stats(g: Graph) -> DataFrame:
    """One row: nodes, edges, edges a node, mean and largest degree."""
    return g.degrees.agg(
        F.count("*").alias("n"),
        (F.sum("deg") / 2).alias("m"),
        (F.sum("deg") / 2 / F.count("*")).alias("m_per_n"),
        F.avg("deg").alias("mean_deg"),
        F.max("deg").alias("max_deg"),
    )


def homophily(g: Graph, truth: DataFrame) -> DataFrame:
    """One row: share of edges whose ends share a label (edges with both ends labelled)."""
    left, right = (truth.select(F.col("node_id").alias(k), F.col("label").alias(f"l_{k}")) for k in ("src", "dst"))
    both = g.edges.select("src", "dst").join(left, "src").join(right, "dst").groupBy("src", "dst").agg(F.max((F.col("l_src") == F.col("l_dst")).cast("int")).alias("same"))
    return both.agg(F.avg("same").alias("homophily"), (F.count("*") / 2).cast("long").alias("labelled_edges"))


def within_hops(g: Graph, seeds: DataFrame, hops: int) -> DataFrame:
    """(seed_id, node_id, hop): nodes reached within ``hops`` steps, at their least distance."""
    ball = seeds.select("seed_id", F.col("seed_id").alias("node_id"), F.lit(0).alias("hop"))
    for h in range(1, hops + 1):
        edge = g.edges.select(F.col("src").alias("node_id"), "dst")
        step = ball.where(F.col("hop") == h - 1).join(edge, "node_id").select("seed_id", F.col("dst").alias("node_id"), F.lit(h).alias("hop"))
        ball = ball.union(step).groupBy("seed_id", "node_id").agg(F.min("hop").alias("hop"))
    return ball


def connected(g: Graph) -> DataFrame:
    """(node_id, component_id): smallest node id of each component.

    Smallest labels spread along edges and along the labels themselves, so the number of rounds is about the logarithm
    of the longest chain; a round cuts lineage and sends one count to the driver.
    """
    edges = materialise(g.edges.select("src", "dst"), "cc_edges")
    labels = materialise(edges.groupBy(F.col("src").alias("node_id")).agg(F.min("dst").alias("m")).select("node_id", F.least("node_id", "m").alias("label")), "cc")
    while True:
        near = edges.join(labels.select(F.col("node_id").alias("dst"), "label"), "dst").groupBy(F.col("src").alias("node_id")).agg(F.min("label").alias("m"))
        low = labels.join(near, "node_id").select("node_id", F.col("label").alias("old"), F.least("label", "m").alias("label"))
        up = labels.select(F.col("node_id").alias("label"), F.col("label").alias("above"))
        after = materialise(low.join(up, "label").select("node_id", "old", F.least("label", "above").alias("label")), "cc")
        changed = after.where("old != label").limit(1).count()
        discard(labels)
        labels = after
        if not changed:
            return labels.select("node_id", F.col("label").alias("component_id"))


def largest_component(g: Graph) -> Graph:
    """The graph on its largest component (of equally large ones, that of the smallest id)."""
    parts = connected(g)
    top = parts.groupBy("component_id").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "component_id").limit(1)
    inside = parts.join(F.broadcast(top), "component_id", "left_semi").select(F.col("node_id").alias("src"))
    return Graph(g.edges.join(inside, "src", "left_semi"))


def degree_deciles(g: Graph) -> DataFrame:
    """(decile, nodes, lo, hi): degree range of each tenth of the nodes, by exact distribution of degrees.

    Ranks come from counts of each degree, of which there are few, not from a sort of all nodes.
    """
    counts = g.degrees.groupBy("deg").agg(F.count("*").alias("n"))
    w = Window.orderBy("deg")
    placed = counts.select("deg", "n", F.sum("n").over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("upto"), F.sum("n").over(w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)).alias("all"))
    decile = F.least(F.lit(9), F.floor((F.col("upto") - 1) * 10 / F.col("all"))).cast("int") + 1
    return placed.groupBy(decile.alias("decile")).agg(F.sum("n").alias("nodes"), F.min("deg").alias("lo"), F.max("deg").alias("hi"))


def ranked_nodes(nodes: DataFrame) -> DataFrame:
    """(node_id, place): distinct nodes numbered from 1 in the order of their ids, without a single task that sees all.

    Nodes are dealt by ranges of ids; the ranges' sizes, one number a partition, are summed on the driver.
    """
    dealt = nodes.select("node_id").distinct().repartitionByRange("node_id")
    dealt = materialise(dealt.withColumn("part", F.spark_partition_id()), "ranked")
    before, total = {}, 0
    for r in sorted(dealt.groupBy("part").agg(F.min("node_id").alias("lo"), F.count("*").alias("n")).collect(), key=lambda r: r.lo):
        before[r.part], total = total, total + r.n
    offsets = nodes.sparkSession.createDataFrame(sorted(before.items()), "part int, before long")
    own = F.row_number().over(Window.partitionBy("part").orderBy("node_id"))
    return dealt.withColumn("own", own).join(F.broadcast(offsets), "part").select("node_id", (F.col("before") + F.col("own")).alias("place"))


def pick_seeds(nodes: DataFrame, n: int) -> DataFrame:
    """(seed_id): ``n`` nodes in the order of a hash, the same on every run and in every engine."""
    ids = nodes.select(F.col("node_id").alias("seed_id"))
    return ids.orderBy(F.md5(F.col("seed_id").cast("string"))).limit(n)
