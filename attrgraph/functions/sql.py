"""SQL names: vector functions, and table functions over a small packed graph."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from attrgraph.operators.graph import Graph, adjacency

SMALL_GRAPH_EDGES = 5_000_000


def register(spark: SparkSession) -> None:
    """vec_dot(a, b) and attr_affinity(z_i, z_j) as SQL expressions of arrays."""
    for name in ("vec_dot", "attr_affinity"):
        spark.sql(f"create or replace temporary function {name}(a array<double>, b array<double>) returns double return aggregate(zip_with(a, b, (x, y) -> x * y), 0d, (s, x) -> s + x)")


def register_graph(spark: SparkSession, g: Graph) -> None:
    """neighbors_within(src, hops) and diffuse_local(seed, alpha, eps) as table functions over a graph of checked size.

    The packed graph goes to every worker, so more than SMALL_GRAPH_EDGES edges raise; larger graphs have
    ``graph.within_hops`` and ``diffusion.diffuse``.
    """
    from attrgraph.session import workers

    workers(spark)
    edges = g.edges.count()
    if edges > SMALL_GRAPH_EDGES:
        raise ValueError(f"{edges} edges are too many for a table function")
    packed = {r.node_id: ([x.dst for x in r.nb], [x.p for x in r.nb]) for r in adjacency(g, 1 << 30).select("node_id", "nb").collect()}
    degree = {r.node_id: r.deg for r in g.degrees.collect()}
    shared = spark.sparkContext.broadcast((packed, degree))

    @F.udtf(returnType="node_id: bigint, hop: int")
    class NeighborsWithin:
        def eval(self, src: int, hops: int) -> Iterator[tuple[int, int]]:
            near, _ = shared.value
            seen, ring = {src}, [src]
            yield src, 0
            for hop in range(1, hops + 1):
                ring = sorted({d for s in ring for d in near.get(s, ((), ()))[0]} - seen)
                seen.update(ring)
                for n in ring:
                    yield n, hop

    @F.udtf(returnType="node_id: bigint, reserve: double, residual: double")
    class DiffuseLocal:
        def eval(self, seed: int, alpha: float, eps: float) -> Iterator[tuple[int, float, float]]:
            near, deg = shared.value
            alpha, eps = float(alpha), float(eps)
            r, kept = ({seed: 1.0} if seed in deg else {}), {}
            while hot := [n for n, x in r.items() if x > 0 and x >= eps * deg[n]]:
                moved = [(n, r.pop(n)) for n in hot]
                for n, x in moved:
                    kept[n] = kept.get(n, 0.0) + (1 - alpha) * x
                    for d, p in zip(*near[n], strict=True):
                        r[d] = r.get(d, 0.0) + alpha * x * p
            for n in sorted(set(kept) | set(r)):
                yield n, kept.get(n, 0.0), r.get(n, 0.0)

    spark.udtf.register("neighbors_within", NeighborsWithin)
    spark.udtf.register("diffuse_local", DiffuseLocal)
