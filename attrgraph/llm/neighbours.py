"""Approximate nearest neighbours over balanced posting lists.

Lists are the cells of a power diagram: a centroid has a weight that is added to squared distances, and k-means on a bounded
sample raises the weights of full lists and lowers those of empty ones until the lists are of similar size. A vector goes to its
own cell's list and, if it lies near a boundary, to further lists that are almost as near. A query finds its centroids by best-first
search over a neighbour graph of the centroids held in memory, keeps the lists whose distance is within a ratio of the
nearest one's (and a least share of all lists), and is compared exactly with the vectors in those. Lists are packed into shards of bounded
size; a list beyond that size (of a very common vector) is dealt over several.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator
from functools import partial

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from attrgraph.session import materialise, workers

SAMPLE = 20_000
LIST_SIZE = 128
MAX_LISTS = 8192
REPLICAS = 4
BOUNDARY_RATIO = 1.10
PROBE_RATIO = 1.07
LEAST_LISTS, LEAST_SHARE = 4, 7
SHARD_ROWS = 4096
QUERY_ROWS = 20_000
K = 10


def distances(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Squared distances, for choosing lists only."""
    return np.maximum((a * a).sum(1)[:, None] - 2 * (a @ b.T) + (b * b).sum(1)[None], 0)


class Centroids:
    """Weighted centroids with a neighbour graph over them."""

    def __init__(self, points: np.ndarray, weights: np.ndarray | None = None, degree: int = 24):
        self.points, self.weights = points, np.zeros(len(points)) if weights is None else weights
        n = len(points)
        near = np.empty((n, min(degree, n - 1)), np.int64)
        for i in range(0, n, 1024):
            d = distances(points[i : i + 1024], points)
            d[np.arange(len(d)), i + np.arange(len(d))] = np.inf
            near[i : i + 1024] = np.argsort(d, axis=1, kind="stable")[:, : near.shape[1]]
        links: list[set[int]] = [set(row.tolist()) for row in near]
        for i in range(n):
            for j in near[i].tolist():
                links[j].add(i)
        reached, order = {0}, [0]
        while len(reached) < n:  # join what isn't connected yet by the nearest pair's rule of thumb: to the entry
            while order:
                for j in links[order.pop()]:
                    if j not in reached:
                        reached.add(j)
                        order.append(j)
            if len(reached) < n:
                lost = next(i for i in range(n) if i not in reached)
                links[0].add(lost)
                links[lost].add(0)
                reached.add(lost)
                order = [lost]
        self.links = [np.array(sorted(x), np.int64) for x in links]

    def search(self, query: np.ndarray, ratio: float, least: int = 1) -> np.ndarray:
        """Centroids within ``ratio`` of the nearest one found, the ``least`` nearest in any case, by best-first search."""
        beam = max(32, least)
        seen = np.zeros(len(self.points), bool)
        seen[0] = True
        d0 = float(((self.points[0] - query) ** 2).sum() + self.weights[0])
        queue, best, found = [(d0, 0)], [-d0], [(d0, 0)]
        low = d0
        while queue:
            d, i = heapq.heappop(queue)
            if d > max(-best[0], low * ratio * ratio) and len(best) >= beam:
                break
            new = self.links[i][~seen[self.links[i]]]
            seen[new] = True
            for dj, j in zip((((self.points[new] - query) ** 2).sum(1) + self.weights[new]).tolist(), new.tolist(), strict=True):
                found.append((dj, j))
                heapq.heappush(queue, (dj, j))
                heapq.heappush(best, -dj)
                if len(best) > beam:
                    heapq.heappop(best)
                low = min(low, dj)
        return np.array([j for place, (dj, j) in enumerate(sorted(found)) if place < least or dj <= low * ratio * ratio + 1e-12], np.int64)


def train(sample: np.ndarray, lists: int, rounds: int = 40) -> tuple[np.ndarray, np.ndarray]:
    """(centroids, weights) whose cells hold similar numbers of the sample; equal vectors can't be told apart."""
    rng = np.random.default_rng(11)
    unique = np.unique(sample, axis=0)
    lists = max(1, min(lists, len(unique)))
    points = unique[rng.permutation(len(unique))[:lists]].copy()
    weights = np.zeros(lists)
    for turn in range(rounds):
        moving = turn < rounds // 2
        sums, counts, near = np.zeros_like(points), np.zeros(lists), []
        for i in range(0, len(sample), 2048):
            block = sample[i : i + 2048]
            d = distances(block, points)
            pick = (d + weights).argmin(axis=1)
            counts += np.bincount(pick, minlength=lists)
            near.append(d.min(axis=1))
            if moving:
                np.add.at(sums, pick, block)
        if moving:
            full = counts > 0
            points[full] = sums[full] / counts[full, None]
            points[~full] = unique[rng.integers(0, len(unique), int((~full).sum()))]
        step = 0.15 * float(np.median(np.concatenate(near))) * (1 if moving else 2 - 2 * turn / rounds)
        weights += step * np.clip(counts / max(1.0, counts.mean()) - 1, -1, 1)
        weights -= weights.min()
    return points, weights


def _stack(column: pd.Series) -> np.ndarray:
    return np.stack(column.to_numpy()).astype(np.float64)


def assign(vectors: np.ndarray, points: np.ndarray, weights: np.ndarray, replicas: int = REPLICAS, ratio: float = BOUNDARY_RATIO) -> list[list[int]]:
    """The lists of each vector, its own cell's first."""
    d = distances(vectors, points) + weights
    top = min(replicas * 2, d.shape[1])
    near = np.argpartition(d, top - 1, axis=1)[:, :top]
    near = np.take_along_axis(near, np.argsort(np.take_along_axis(d, near, 1), axis=1, kind="stable"), 1)
    out = []
    for row, order in zip(d, near.tolist(), strict=True):
        chosen, limit = order[:1], row[order[0]] * ratio * ratio
        for j in order[1:]:
            if row[j] > limit or len(chosen) == replicas:
                break
            chosen.append(j)
        out.append(chosen)
    return out


def _post(frames: Iterator[pd.DataFrame], points: np.ndarray, weights: np.ndarray) -> Iterator[pd.DataFrame]:
    for pdf in frames:
        for i in range(0, len(pdf), 1024):
            some = pdf.iloc[i : i + 1024]
            lists = assign(_stack(some["embedding"]), points, weights)
            yield some.assign(list=lists).explode("list").astype({"list": "int32"})[["vec_id", "embedding", "list"]]


def _probe(frames: Iterator[pd.DataFrame], points: np.ndarray, weights: np.ndarray, shards: dict[int, list[int]], ratio: float, least: int) -> Iterator[pd.DataFrame]:
    graph = Centroids(points, weights)
    for pdf in frames:
        rows = []
        for vec_id, v in zip(pdf["vec_id"], pdf["embedding"], strict=True):
            mine: dict[int, list[int]] = {}
            for c in graph.search(np.asarray(v, np.float64), ratio, least).tolist():
                for s in shards.get(c, ()):
                    mine.setdefault(s, []).append(c)
            rows += [(vec_id, v, s, lists) for s, lists in mine.items()]
        yield pd.DataFrame(rows, columns=["query_id", "query", "shard", "lists"])


def nearest(ids: np.ndarray, vectors: np.ndarray, query_ids: np.ndarray, queries: np.ndarray, k: int) -> list[tuple[int, int, float]]:
    """The k nearest (distance, then id) rows of other ids for each query; the same id counts once."""
    order = np.argsort(ids, kind="stable")
    ids, vectors = ids[order], vectors[order]
    out = []
    for q, v in zip(query_ids.tolist(), queries, strict=True):
        d = np.sqrt(((vectors - v) ** 2).sum(axis=1))
        limit = np.partition(d, min(len(d) - 1, 2 * k))[min(len(d) - 1, 2 * k)]
        seen: set[int] = {q}
        for keep in (np.flatnonzero(d <= limit), np.arange(len(d))):
            seen, rows = {q}, []
            for i in keep[np.argsort(d[keep], kind="stable")].tolist():
                if int(ids[i]) not in seen:
                    seen.add(int(ids[i]))
                    rows.append((q, int(ids[i]), float(d[i])))
                    if len(rows) == k:
                        break
            if len(rows) == k:
                break
        out += rows
    return out


def _compare(vectors: pd.DataFrame, queries: pd.DataFrame, k: int) -> pd.DataFrame:
    if not len(vectors) or not len(queries):
        return pd.DataFrame({"query_id": [], "vec_id": [], "score": []}).astype({"query_id": "int64", "vec_id": "int64", "score": "float64"})
    ids, x, of = vectors["vec_id"].to_numpy(), _stack(vectors["embedding"]), vectors["list"].to_numpy()
    order = np.argsort(of, kind="stable")
    of, first = np.unique(of[order], return_index=True)
    place = dict(zip(of.tolist(), np.split(order, first[1:]), strict=True))
    rows = []
    for q, v, lists in zip(queries["query_id"].to_numpy(), _stack(queries["query"]), queries["lists"], strict=True):
        pick = [place[c] for c in lists if c in place]
        if pick:
            pick = np.concatenate(pick)
            rows += nearest(ids[pick], x[pick], np.array([q]), v[None], k)
    return pd.DataFrame(rows, columns=["query_id", "vec_id", "score"]).astype({"query_id": "int64", "vec_id": "int64", "score": "float64"})


def _brute(frames: Iterator[pd.DataFrame], queries: list[tuple[int, list[float]]], k: int) -> Iterator[pd.DataFrame]:
    ids, vectors = np.array([q for q, _ in queries]), np.array([v for _, v in queries], np.float64)
    for pdf in frames:
        for i in range(0, len(pdf), SHARD_ROWS):
            some = pdf.iloc[i : i + SHARD_ROWS]
            yield pd.DataFrame(nearest(some["vec_id"].to_numpy(), _stack(some["embedding"]), ids, vectors, k), columns=["query_id", "vec_id", "score"])


_FOUND = "query_id long, vec_id long, score double"


def _ranked(found: DataFrame, k: int) -> DataFrame:
    best = found.groupBy("query_id", "vec_id").agg(F.min("score").alias("score"))
    order = Window.partitionBy("query_id").orderBy("score", "vec_id")
    return best.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")


def usable(vectors: DataFrame) -> DataFrame:
    """(vec_id, embedding) rows that take part: of the commonest length (the longest of equally common ones), with an id,
    finite, and not zero."""
    good = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast("array<double>").alias("embedding"))
    finite = F.forall("embedding", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    good = good.where(F.col("vec_id").isNotNull() & F.col("embedding").isNotNull() & finite & F.exists("embedding", lambda x: x != 0))
    width = good.groupBy(F.size("embedding").alias("n")).agg(F.count("*").alias("c")).orderBy(F.desc("c"), F.desc("n")).first()
    return good.where(F.size("embedding") == (width.n if width else 0))


def search(vectors: DataFrame, every: int = 100, k: int = K, list_size: int = LIST_SIZE, ratio: float = PROBE_RATIO, query_block: int = 2000, most_lists: int = MAX_LISTS, sample_size: int = SAMPLE) -> DataFrame:
    """query_id, rank, vec_id, score: for each vector whose id is divisible by ``every``, its k nearest found others.

    Distances are Euclidean in double precision on the original vectors, ties go to the smaller vec_id. Rows of one
    vec_id count as one candidate, at its least distance, and as one query, with the least of its vectors in array order. Centroids
    are fitted on about ``sample_size`` vectors, drawn by a hash of vec_id; every vector is in the lists. Lists hold about
    ``list_size`` vectors as long as that takes no more than ``most_lists`` centroids, then more. A query that the lists give fewer than k answers is compared
    with all vectors, in blocks of ``query_block`` queries, so fewer come back only if there are fewer. Nulls, zeros and
    non-finite components take no part; other columns are ignored; an empty table gives an empty result.
    """
    spark = workers(vectors.sparkSession)
    rows = usable(vectors)
    narrow = rows.select("vec_id", F.transform("embedding", lambda x: x.cast("float")).alias("embedding"))
    single = narrow  # stored as given: float32 in the source; doubles that float can't hold stay doubles
    if dict(vectors.dtypes).get("embedding") != "array<float>":
        single = rows
    stats = rows.agg(F.count("*").alias("n")).first()
    if not stats.n:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    share = min(1.0, sample_size / stats.n)
    drawn = rows.where(F.pmod(F.xxhash64("vec_id"), F.lit(1 << 30)) <= int(share * (1 << 30))) if share < 1 else rows
    sample = drawn.groupBy("vec_id").agg(F.min("embedding").alias("embedding")).toPandas().sort_values("vec_id")
    if not len(sample):
        sample = rows.limit(1).toPandas()
    points, weights = train(_stack(sample["embedding"]), min(most_lists, max(1, stats.n // list_size)))
    kind = single.schema["embedding"].dataType.simpleString()
    posted = materialise(single.mapInPandas(partial(_post, points=points, weights=weights), f"vec_id long, embedding {kind}, list int"), "postings")
    sizes = {r.list: r.n for r in posted.groupBy("list").agg(F.count("*").alias("n")).collect()}
    shards, base, parts, filled = {}, {}, {}, SHARD_ROWS
    shard = -1
    for c in sorted(sizes):
        pieces = -(-sizes[c] // SHARD_ROWS)
        if pieces == 1 and filled + sizes[c] <= SHARD_ROWS:
            filled += sizes[c]
        else:
            shard, filled = shard + 1, sizes[c] if pieces == 1 else SHARD_ROWS
        base[c], parts[c] = shard, pieces
        shards[c] = list(range(shard, shard + pieces))
        shard += pieces - 1
    layout = spark.createDataFrame([(c, base[c], parts[c]) for c in sorted(sizes)], "list int, base int, parts int")
    dealt = posted.join(F.broadcast(layout), "list").withColumn("shard", (F.col("base") + F.pmod(F.xxhash64("vec_id"), F.col("parts"))).cast("int"))
    queries = materialise(single.where(F.col("vec_id") % every == 0).groupBy("vec_id").agg(F.min("embedding").alias("embedding")), "queries")
    least = max(LEAST_LISTS, -(-len(points) // LEAST_SHARE))
    probes = queries.mapInPandas(partial(_probe, points=points, weights=weights, shards=shards, ratio=ratio, least=least), f"query_id long, query {kind}, shard int, lists array<int>")
    # a shard's vectors meet its queries in blocks, so that no task holds more than about QUERY_ROWS of them
    turns = -(-queries.count() // QUERY_ROWS)
    dealt = dealt.select("shard", "list", "vec_id", "embedding", F.explode(F.sequence(F.lit(0), F.lit(max(0, turns - 1)))).alias("turn"))
    probes = probes.withColumn("turn", F.pmod(F.xxhash64("query_id"), F.lit(max(1, turns))).cast("int"))
    compare = lambda a, b: _compare(a, b, k)
    found = dealt.groupBy("shard", "turn").cogroup(probes.groupBy("shard", "turn")).applyInPandas(compare, _FOUND)
    ranked = materialise(_ranked(found, k), "nearest")
    counts = ranked.groupBy("query_id").agg(F.count("*").alias("n"))
    lacking = queries.join(counts, queries.vec_id == counts.query_id, "left").where(F.coalesce("n", F.lit(0)) < min(k, stats.n - 1)).select("vec_id", "embedding")
    missing = sorted(r.vec_id for r in lacking.select("vec_id").collect())
    out = ranked
    for i in range(0, len(missing), query_block):
        ids = missing[i : i + query_block]
        block = [(r.vec_id, list(r.embedding)) for r in queries.where(F.col("vec_id").isin(ids)).collect()]
        more = _ranked(single.mapInPandas(partial(_brute, queries=block, k=k), _FOUND), k)
        out = out.where(~F.col("query_id").isin(ids)).union(more)
    return out
