"""Exact diffusion on a small graph that every worker holds as a whole, component by component."""

from __future__ import annotations

from collections.abc import Iterator
from functools import partial

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame

from attrgraph.operators.graph import Graph
from attrgraph.session import materialise, workers


class Whole:
    """Nodes and directed edges of a graph, numbered and sorted by component."""

    def __init__(self, edges: pd.DataFrame):
        nodes = np.unique(edges["src"].to_numpy())
        src, dst = np.searchsorted(nodes, edges["src"]), np.searchsorted(nodes, edges["dst"])
        label = np.arange(len(nodes))
        while True:
            low = label.copy()
            np.minimum.at(low, src, label[dst])
            low = low[low]
            if (low == label).all():
                break
            label = low
        order = np.lexsort((nodes, label))  # nodes of a component stand together
        place = np.empty(len(nodes), np.int64)
        place[order] = np.arange(len(nodes))
        self.nodes, self.label = nodes[order], label[order]
        by = np.argsort(place[src], kind="stable")
        self.src, self.dst, self.w = place[src][by], place[dst][by], edges["w"].to_numpy(float)[by]
        self.deg = np.bincount(self.src, self.w, len(nodes))
        self.sorted, self.at = nodes, place

    def places(self, ids: np.ndarray) -> np.ndarray:
        """Numbers of nodes; -1 for those without edges."""
        i = np.minimum(np.searchsorted(self.sorted, ids), max(0, len(self.sorted) - 1))
        return np.where(self.sorted[i] == ids, self.at[i], -1) if len(self.sorted) else np.full(len(ids), -1)

    def part(self, label: int) -> tuple[int, int, np.ndarray, np.ndarray, np.ndarray]:
        """(first node, last node + 1, src, dst, w) of a component; ends are numbered from its first node."""
        lo, hi = np.searchsorted(self.label, [label, label + 1])
        a, b = np.searchsorted(self.src, [lo, hi])
        return lo, hi, self.src[a:b] - lo, self.dst[a:b] - lo, self.w[a:b]

    def shares(self, lo: int, src: np.ndarray, dst: np.ndarray, w: np.ndarray, norm: str) -> np.ndarray:
        return w / {"walk": self.deg[src + lo], "reverse": self.deg[dst + lo], "sym": np.sqrt(self.deg[src + lo] * self.deg[dst + lo])}[norm]


def _levels(m: np.ndarray, reached: np.ndarray, src: np.ndarray, dst: np.ndarray, p: np.ndarray, alpha: float, steps: int) -> np.ndarray:
    """Sum of the levels; ``reached`` is filled in place."""
    total, grows = (1 - alpha) * m, True
    for _ in range(steps):
        m = alpha * np.bincount(dst, m[src] * p, len(m))
        total += (1 - alpha) * m
        if grows:
            before = reached.sum()
            reached[dst[reached[src]]] = True
            grows = reached.sum() > before
    return total


def _diffused(key: tuple, pdf: pd.DataFrame, sent, alpha: float, steps: int, norm: str) -> pd.DataFrame:
    whole: Whole = sent.value
    ids, mass = pdf["node_id"].to_numpy(), pdf["mass"].to_numpy(float)
    at = whole.places(ids)
    nodes, scores = [ids[at < 0]], [(1 - alpha) * mass[at < 0]]
    for label in np.unique(whole.label[at[at >= 0]]):
        lo, hi, src, dst, w = whole.part(label)
        mine = (at >= lo) & (at < hi)
        m = np.bincount(at[mine] - lo, mass[mine], hi - lo)
        reached = np.zeros(hi - lo, bool)
        reached[at[mine] - lo] = True
        total = _levels(m, reached, src, dst, whole.shares(lo, src, dst, w, norm), alpha, steps)
        nodes.append(whole.nodes[lo:hi][reached])
        scores.append(total[reached])
    return pd.DataFrame({"seed_id": key[0], "node_id": np.concatenate(nodes), "score": np.concatenate(scores)})


def _send(g: Graph):
    spark = workers(g.edges.sparkSession)
    return spark.sparkContext.broadcast(Whole(g.edges.select("src", "dst", "w").toPandas()))


def diffuse(g: Graph, start: DataFrame, alpha: float, steps: int, norm: str) -> DataFrame:
    """As ``exact.diffuse``: all levels of a seed in one worker."""
    kinds = dict(start.dtypes)
    run = partial(_diffused, sent=_send(g), alpha=alpha, steps=steps, norm=norm)
    rows = start.groupBy("seed_id", "node_id").agg({"mass": "sum"}).toDF("seed_id", "node_id", "mass")
    return materialise(rows.groupBy("seed_id").applyInPandas(lambda key, pdf: run(key, pdf), f"seed_id {kinds['seed_id']}, node_id {kinds['node_id']}, score double"), "walk")


def _gaps(frames: Iterator[pd.DataFrame], sent, wanted, alpha: float, steps: int) -> Iterator[pd.DataFrame]:
    whole: Whole = sent.value
    for pdf in frames:
        for a in pdf["seed_id"].to_numpy():
            at = int(whole.places(np.array([a]))[0])
            if at < 0:
                continue
            lo, hi, src, dst, w = whole.part(whole.label[at])
            start, reached, again = np.zeros(hi - lo), np.zeros(hi - lo, bool), np.zeros(hi - lo, bool)
            start[at - lo], reached[at - lo], again[at - lo] = 1.0, True, True
            there = _levels(start, reached, src, dst, whole.shares(lo, src, dst, w, "walk"), alpha, steps)
            back = _levels(start, again, src, dst, whole.shares(lo, src, dst, w, "reverse"), alpha, steps)
            b = whole.nodes[lo:hi]
            told = reached & again & (b > a) & wanted.value[lo:hi]
            yield pd.DataFrame({"a": a, "b": b[told], "gap": np.abs(there * whole.deg[at] - back * whole.deg[lo:hi])[told]})


def symmetry_gaps(g: Graph, seeds: DataFrame, alpha: float, steps: int) -> DataFrame:
    """As ``exact.check_symmetry``: a seed's walk and the walks of all nodes that end at it (the transposed steps), side by side."""
    sent = _send(g)
    held = np.zeros(len(sent.value.nodes), bool)
    at = sent.value.places(seeds.toPandas()["seed_id"].to_numpy())
    held[at[at >= 0]] = True
    kind = dict(seeds.dtypes)["seed_id"]
    spread = seeds.select("seed_id").repartition(4 * g.edges.sparkSession.sparkContext.defaultParallelism, "seed_id")
    return spread.mapInPandas(partial(_gaps, sent=sent, wanted=g.edges.sparkSession.sparkContext.broadcast(held), alpha=alpha, steps=steps), f"a {kind}, b {kind}, gap double")
