"""Diffusion of each seed in one NumPy worker over the neighbourhood that it has explored.

A seed's rounds run in its worker until a node must move whose adjacency isn't there; the worker then names that node, and those
that may soon move. The named nodes' adjacency is fetched for all seeds in one join, and the seeds go on. So there are as many
jobs as fetches, not as rounds, and of the graph only the buckets of explored nodes are read. A seed that
explores more than ``MOST_EDGES`` edges goes to the engine of ``diffusion`` that keeps its state in tables.
"""

from __future__ import annotations

from collections.abc import Callable
from functools import partial
from math import exp, factorial

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from attrgraph.operators.graph import BROADCAST_BYTES, ROW_BYTES, Graph
from attrgraph.session import materialise, workers

MOST_EDGES = 2_000_000
#: A graph of at most so many directed edges, some 10 MB, may be sent to all workers as a whole.
WHOLE_EDGES = 200_000
#: Nodes are fetched ahead when they have this share of what makes them hot.
AHEAD = 0.25
#: A whole component is given at most this share of what it can hold: flow of more mass never settles.
HOLDS = 0.9
DONE, WANTED, LARGE, FAILED = 0, 1, 2, 3


def _joined(column: pd.Series, kind: type) -> np.ndarray:
    return np.concatenate([np.asarray(x, kind) for x in column]) if len(column) else np.empty(0, kind)


def fetching(g: Graph, state: DataFrame, wanted: DataFrame, schema: str, run: Callable[[pd.DataFrame, pd.DataFrame], pd.DataFrame], failure: str = "", whole: bool = False) -> tuple[DataFrame, DataFrame | None]:
    """(results, seeds whose neighbourhood is too large or None) of ``run`` for each seed of the written ``state``.

    ``run`` gets a seed's adjacency so far (node_id, dst, p, d) and its start rows. It returns rows of ``schema`` after seed_id, with a
    last column kind: results, or the nodes that it lacks. Those are fetched, and the seed runs again. A row of kind FAILED is an
    error here, with the text ``failure``. With ``whole``, a graph of at most ``WHOLE_EDGES`` edges is broadcast, and nothing fetched.
    """
    workers(state.sparkSession)
    kinds = dict(state.dtypes)
    schema = f"seed_id {kinds['seed_id']}, node_id {kinds['node_id']}, {schema}, kind int"
    empty = pd.DataFrame({"node_id": pd.Series([], dtype=object), "dst": [], "p": [], "d": []})

    def gathered(key: tuple, near: pd.DataFrame, start: pd.DataFrame) -> pd.DataFrame:
        if not len(start):
            return pd.DataFrame({c.split()[0]: [] for c in schema.split(", ")})
        out = run(near if len(near) else empty, start)
        out.insert(0, "seed_id", key[0])
        return out

    if whole and g.size <= WHOLE_EDGES:
        rows = g.packed.rows.select("node_id", F.col("nb.dst").alias("dst"), F.col("nb.p").alias("p"), F.col("nb.deg").alias("d"))
        sent = state.sparkSession.sparkContext.broadcast(rows.toPandas())
        told = state.groupBy("seed_id").applyInPandas(lambda key, start: gathered(key, sent.value, start), schema)
        return materialise(told, "told").drop("kind"), None
    open_seeds, fetched, out, large = state, None, None, None
    wanted = materialise(wanted, "wanted")
    while True:
        nodes = materialise(wanted.select("node_id").distinct(), "nodes")
        rows = g.packed.of(nodes).select("node_id", F.col("nb.dst").alias("dst"), F.col("nb.p").alias("p"), F.col("nb.deg").alias("d"))
        small = wanted.count() * ROW_BYTES <= BROADCAST_BYTES
        new = materialise(rows.join(F.broadcast(wanted) if small else wanted, "node_id").select("seed_id", "node_id", "dst", "p", "d"), "near")
        near = fetched = new if fetched is None else fetched.union(new)
        if open_seeds is not state:
            near = near.join(going, "seed_id", "left_semi")
        told = materialise(near.groupBy("seed_id").cogroup(open_seeds.groupBy("seed_id")).applyInPandas(gathered, schema), "told")
        done = told.where(F.col("kind") == DONE).drop("kind")
        out = done if out is None else out.union(done)
        left = {r.kind for r in told.where(F.col("kind") != DONE).select("kind").distinct().collect()}
        if FAILED in left:
            raise RuntimeError(failure)
        if LARGE in left:
            more = told.where(F.col("kind") == LARGE).select("seed_id").distinct()
            large = more if large is None else large.union(more)
        if WANTED not in left:
            return out, large
        wanted = told.where(F.col("kind") == WANTED).select("seed_id", "node_id")
        going = wanted.select("seed_id").distinct()
        open_seeds = state.join(going, "seed_id", "left_semi")


class Neighbourhood:
    """A seed's fetched adjacency and start in dense numbers: ``nodes`` by number, edges ``src`` to ``dst`` with ``share`` = w / degree of
    src, degrees, which nodes' edges are here (``inner``), and the numbers of the start rows (``first``)."""

    def __init__(self, near: pd.DataFrame, start: pd.DataFrame):
        own = start["node_id"].to_numpy()
        to, self.share, to_deg = _joined(near["dst"], own.dtype), _joined(near["p"], float), _joined(near["d"], float)
        sizes = np.array([len(x) for x in near["dst"]], np.int64)
        self.nodes, place = np.unique(np.concatenate([own, near["node_id"].to_numpy(own.dtype), to]), return_inverse=True)
        self.n = len(self.nodes)
        self.first, held, self.dst = place[: len(own)], place[len(own) : len(own) + len(near)], place[len(own) + len(near) :]
        self.src = np.repeat(held, sizes)
        self.deg = np.zeros(self.n)
        self.deg[self.dst], self.deg[self.first] = to_deg, start["deg"]
        self.inner = np.zeros(self.n, bool)
        self.inner[held] = True

    def lacking(self, nodes: np.ndarray, most_edges: int, **columns: float) -> pd.DataFrame:
        """Rows that ask for the adjacency of ``nodes``, or say that it would be too much."""
        kind = WANTED if not len(self.dst) or len(self.dst) + self.deg[nodes].sum() <= most_edges else LARGE
        return pd.DataFrame({"node_id": self.nodes[nodes], **columns, "kind": kind})


def _run(near: pd.DataFrame, start: pd.DataFrame, alpha: float, sigma: float, most_edges: int, most_rounds: int | None = None) -> pd.DataFrame:
    """One seed's rounds; its state, or the nodes that it lacks."""
    eps, budget = float(start["eps"].iloc[0]), float(start["budget"].iloc[0])
    b = Neighbourhood(near, start)
    r, kept, spent = np.zeros(b.n), np.zeros(b.n), 0.0
    r[b.first] = start["residual"]
    done = 0
    while most_rounds is None or done < most_rounds:
        some = r > 0
        active = some & (r >= eps * b.deg)
        if not active.any():
            break
        volume = b.deg[some].sum()
        now = spent
        if active.sum() / some.sum() > sigma and spent + volume < budget:
            active, now = some, spent + volume
        if (active & ~b.inner).any():
            told = ~b.inner & (active | (some & (r >= AHEAD * eps * b.deg)))
            return b.lacking(told, most_edges, deg=0.0, residual=0.0, reserve=0.0, eps=eps, budget=budget, spent=0.0)
        spent, done = now, done + 1
        moved = np.where(active, r, 0.0)
        kept += (1 - alpha) * moved
        r = r - moved + np.bincount(b.dst, alpha * moved[b.src] * b.share, b.n)
    told = (kept > 0) | (r > 0)
    return pd.DataFrame({"node_id": b.nodes[told], "deg": b.deg[told], "residual": r[told], "reserve": kept[told], "eps": eps, "budget": budget, "spent": spent, "kind": DONE})


def diffuse_in_balls(g: Graph, state: DataFrame, alpha: float, sigma: float, most_edges: int | None = None, most_rounds: int | None = None) -> DataFrame:
    """The state of ``diffusion.diffuse`` after its last round, from a written state before its first."""
    from attrgraph.operators import diffusion

    run = partial(_run, alpha=alpha, sigma=sigma, most_edges=MOST_EDGES if most_edges is None else most_edges, most_rounds=most_rounds)
    wanted = state.where((F.col("residual") > 0) & (F.col("residual") >= AHEAD * F.col("eps") * F.col("deg"))).select("seed_id", "node_id")
    out, large = fetching(g, state, wanted, "deg double, residual double, reserve double, eps double, budget double, spent double", run, whole=g.whole)
    if large is not None:
        out = out.union(diffusion.run_rounds(g, materialise(state.join(large, "seed_id", "left_semi"), "state"), alpha, sigma, most_rounds=most_rounds))
    return out.select(*diffusion.STATE)


def heat_level_bounds(t: float, n: int) -> list[float]:
    """psi_j, the weight that mass at level j still spreads with."""
    return [sum(t**m * factorial(j) / factorial(m + j) for m in range(n - j + 1)) for j in range(n + 1)]


def run_heat(near: pd.DataFrame, start: pd.DataFrame, t: float, most_edges: int, degree: Callable[[float, float], int]) -> pd.DataFrame:
    eps, b = float(start["eps"].iloc[0]), Neighbourhood(near, start)
    n = degree(t, eps)
    psi = heat_level_bounds(t, n)
    r, total = np.zeros(b.n), np.zeros(b.n)
    r[b.first] = 1.0
    for j in range(n + 1):
        active = r > 0
        if j < n:
            bound = b.deg * (exp(t) * eps / (2 * n * psi[j]))
            active &= r >= bound
            if (active & ~b.inner).any():
                return b.lacking(~b.inner & (r > 0) & (r >= AHEAD * bound), most_edges, score=0.0)
        moved = np.where(active, r, 0.0)
        total += moved
        r = np.bincount(b.dst, t / (j + 1) * moved[b.src] * b.share, b.n)
    told = total > 0
    return pd.DataFrame({"node_id": b.nodes[told], "score": exp(-t) * total[told] / b.deg[told], "kind": DONE})


def run_flow(near: pd.DataFrame, start: pd.DataFrame, p: float, tol: float, rounds: int, bisections: int, settle: bool, most_edges: int) -> pd.DataFrame:
    """Potentials of the p-norm flow: see ``flow.pnorm_flow``."""
    b, q1 = Neighbourhood(near, start), 1.0 / (p - 1.0)
    source, x, w = np.zeros(b.n), np.zeros(b.n), b.share * b.deg[b.src]
    source[b.first] = start["source"]
    if b.inner.all() and source.sum() > HOLDS * b.deg.sum():
        source *= HOLDS * b.deg.sum() / source.sum()
    outer = ~b.inner[b.dst]  # an edge to a node whose own edges aren't here brings its inflow

    def net(at: np.ndarray) -> np.ndarray:
        d = at[b.src] - x[b.dst]
        f = w * np.sign(d) * np.abs(d) ** q1
        return np.bincount(b.src, f, b.n) - np.bincount(b.dst, np.where(outer, f, 0.0), b.n)

    settled = False
    for _ in range(rounds):
        excess = source - net(x) - b.deg
        if not (excess > tol * b.deg).any():
            settled = True
            break
        up = excess > 0
        if (up & ~b.inner).any():
            return b.lacking(~b.inner & (excess > (AHEAD - 1) * b.deg), most_edges, score=0.0, excess=0.0)
        if p == 2:
            balanced = x + excess / b.deg
        else:
            highest = np.zeros(b.n)
            np.maximum.at(highest, b.src, x[b.dst])
            lo, hi = x.copy(), np.maximum(x, highest) + (source + np.abs(excess)) ** (p - 1.0) + 1
            for _ in range(bisections):
                mid = (lo + hi) / 2
                over = source - net(mid) > b.deg
                lo, hi = np.where(over, mid, lo), np.where(over, hi, mid)
            balanced = (lo + hi) / 2
        x = np.where(up, x + (1.0 if p == 2 else 0.5) * (balanced - x), x)
    told = x > 0
    return pd.DataFrame({"node_id": b.nodes[told], "score": x[told], "excess": (source - net(x) - b.deg)[told], "kind": FAILED if settle and not settled else DONE})


def run_release(near: pd.DataFrame, start: pd.DataFrame, capacity: float, height: int, iterations: int, rounds: int, most_edges: int) -> pd.DataFrame:
    """Mass and labels of a seed: see ``flow.capacity_release``."""
    b = Neighbourhood(near, start)
    mass, label, live = np.zeros(b.n), np.zeros(b.n, np.int64), True
    mass[b.first] = 2 * b.deg[b.first]
    key = b.src * np.int64(b.n) + b.dst
    order = np.argsort(key)
    at = np.searchsorted(key[order], b.dst * np.int64(b.n) + b.src)
    at = np.minimum(at, max(0, len(key) - 1))
    back = np.where(key[order][at] == b.dst * np.int64(b.n) + b.src, order[at], -1) if len(key) else at
    for it in range(iterations):
        flow = np.zeros(len(key))
        for _ in range(rounds):
            excess = np.maximum(mass - b.deg, 0.0)
            over = (excess > 0) & live
            if not (over & (label < height)).any() and not (over & (label > 0)).any():
                break
            if (over & ~b.inner).any():
                return b.lacking((mass > 0) & ~b.inner, most_edges, mass=0.0, label=0, score=0.0)
            room = np.where(over[b.src] & (label[b.src] > 0) & (label[b.dst] == label[b.src] - 1), capacity - flow, 0.0)
            room = np.where(room > 1e-12, room, 0.0)
            rooms = np.bincount(b.src, room, b.n)
            sent = room * np.minimum(1.0, excess / np.where(rooms > 0, rooms, 1.0))[b.src]
            mass = mass - np.bincount(b.src, sent, b.n) + np.bincount(b.dst, sent, b.n)
            label = label + (over & (rooms == 0) & (label < height))
            flow += sent
            known = back >= 0
            flow -= np.bincount(back[known], sent[known], len(key))
        if np.maximum(mass - b.deg, 0.0).sum() > 0.5 * mass.sum():
            live = False
        if it < iterations - 1 and live:
            mass, label = 2 * mass, np.zeros(b.n, np.int64)
        if not live:
            break
    told = mass > 0
    return pd.DataFrame({"node_id": b.nodes[told], "mass": mass[told], "label": label[told].astype(np.int32), "score": label[told] + np.minimum(1.0, mass[told] / b.deg[told]), "kind": DONE})
