"""Factor tables: rows z with z_i . z_j equal (or close) to the normalised affinity of nodes i and j."""

from __future__ import annotations

from collections.abc import Iterator
from functools import partial

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from attrgraph.functions import gaussian_hash, vec_dot, vec_scale
from attrgraph.session import materialise, workers

GRAM_LIMIT = 2000


def _signed(v: np.ndarray) -> np.ndarray:
    """Columns with their largest entry positive."""
    top = np.abs(v).argmax(axis=0)
    return v * np.where(v[top, np.arange(v.shape[1])] < 0, -1.0, 1.0)


def gram(attrs: DataFrame) -> tuple[list[str], np.ndarray]:
    """Attribute names and X^T X: summed by pairs of attributes present in one node, d * d numbers in all."""
    names = sorted(r.attr for r in attrs.select("attr").distinct().collect())
    if len(names) > GRAM_LIMIT:
        raise ValueError(f"{len(names)} attributes: use the randomized route")
    packed = attrs.groupBy("node_id").agg(F.collect_list(F.struct("attr", "value")).alias("r"))
    pairs = packed.select(F.explode("r").alias("p"), "r").select("p", F.explode("r").alias("q")).where("p.attr <= q.attr")
    place = {n: i for i, n in enumerate(names)}
    out = np.zeros((len(names), len(names)))
    for r in pairs.groupBy(F.col("p.attr").alias("a"), F.col("q.attr").alias("b")).agg(F.sum(F.col("p.value") * F.col("q.value")).alias("s")).collect():
        out[place[r.a], place[r.b]] = out[place[r.b], place[r.a]] = r.s
    return names, out


def truncated_svd(attrs: DataFrame, k: int, method: str = "gram", power: int = 2, seed: int = 1, extra: int = 8) -> tuple[DataFrame, np.ndarray]:
    """(basis(attr, v: array of k), singular values) of the tall rows (node_id, attr, value).

    ``gram`` sums X^T X and takes its leading eigenvectors on the driver (up to GRAM_LIMIT attributes). ``randomized`` sketches
    with normal numbers hashed from the attribute's name, does ``power`` passes of X^T X, each orthonormalised through a small
    Gram matrix, and never holds more than (k + extra)^2 numbers on the driver. ``auto`` is ``gram`` where that limit allows
    it, else ``randomized``. ``exact_small`` collects X, for tests.
    """
    spark = attrs.sparkSession
    if method == "auto":
        method = "gram" if attrs.select("attr").distinct().count() <= GRAM_LIMIT else "randomized"
    if method == "exact_small":
        table = attrs.toPandas().pivot_table(index="node_id", columns="attr", values="value", fill_value=0.0)
        _, s, vt = np.linalg.svd(table.to_numpy(), full_matrices=False)
        names, v, values = list(table.columns), vt.T[:, :k], s[:k]
    elif method == "gram":
        names, g = gram(attrs)
        w, v = np.linalg.eigh(g)
        order = np.argsort(w)[::-1][:k]
        values, v = np.sqrt(np.maximum(w[order], 0)), v[:, order]
    elif method == "randomized":
        return _randomized(attrs, k, power, seed, extra)
    else:
        raise ValueError(f"no method {method}")
    v = _signed(v)
    return spark.createDataFrame([(n, [float(x) for x in row]) for n, row in zip(names, v, strict=True)], "attr string, v array<double>"), values


def _times(attrs: DataFrame, table: DataFrame, key: str, other: str) -> DataFrame:
    """Sum of value * v by ``other`` of attrs joined with (key, v): one factor of a pass through X^T X."""
    width = len(table.first().v)
    joined = attrs.join(table, key)
    return joined.groupBy(other).agg(F.array(*[F.sum(F.col("value") * F.col("v")[i]) for i in range(width)]).alias("v"))


def _gram_parts(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    total = None
    for pdf in frames:
        if len(pdf):
            v = np.stack(pdf["v"].to_numpy())
            total = v.T @ v if total is None else total + v.T @ v
    if total is not None:
        yield pd.DataFrame({"place": np.arange(total.size), "s": total.ravel()})


def _small_gram(table: DataFrame, width: int) -> np.ndarray:
    """V^T V of (.., v): width^2 sums, each partition's added up in NumPy and those of all partitions by place."""
    workers(table.sparkSession)
    parts = table.select("v").mapInPandas(_gram_parts, "place long, s double")
    out = np.zeros(width * width)
    for r in parts.groupBy("place").agg(F.sum("s").alias("s")).collect():
        out[r.place] = r.s
    return out.reshape(width, width)


def _turned(frames: Iterator[pd.DataFrame], key: str, m: np.ndarray) -> Iterator[pd.DataFrame]:
    for pdf in frames:
        if len(pdf):
            yield pd.DataFrame({key: pdf[key], "v": list(np.stack(pdf["v"].to_numpy()) @ m)})


def _rotated(table: DataFrame, key: str, m: np.ndarray) -> DataFrame:
    workers(table.sparkSession)
    return table.select(key, "v").mapInPandas(partial(_turned, key=key, m=m), f"{key} {dict(table.dtypes)[key]}, v array<double>")


def _randomized(attrs: DataFrame, k: int, power: int, seed: int, extra: int) -> tuple[DataFrame, np.ndarray]:
    width = k + extra
    names = attrs.select("attr").distinct()
    v = names.select("attr", F.array(*[gaussian_hash(F.lit(seed), F.col("attr"), F.lit(j)) for j in range(width)]).alias("v"))
    for _ in range(power + 1):
        v = materialise(_times(attrs, materialise(_times(attrs, v, "attr", "node_id"), "sketch"), "node_id", "attr"), "sketch")
        w, q = np.linalg.eigh(_small_gram(v, width))
        keep = w > max(w.max(), 0) * 1e-14
        v = materialise(_rotated(v, "attr", q[:, keep] / np.sqrt(w[keep])), "basis")
        width = int(keep.sum())
    image = materialise(_times(attrs, v, "attr", "node_id"), "image")
    w, q = np.linalg.eigh(_small_gram(image, width))
    order = np.argsort(w)[::-1][:k]
    basis = materialise(_rotated(v, "attr", q[:, order]), "basis")
    top = basis.agg(*[F.max_by(F.col("v")[i], F.struct(F.abs(F.col("v")[i]), "attr")).alias(f"t{i}") for i in range(len(order))]).first()
    signs = [-1.0 if top[f"t{i}"] < 0 else 1.0 for i in range(len(order))]
    return basis.select("attr", F.zip_with("v", F.lit(signs), lambda x, y: x * y).alias("v")), np.sqrt(np.maximum(w[order], 0))


def project(attrs: DataFrame, basis: DataFrame) -> DataFrame:
    """(node_id, y): rows times the basis; the basis goes to every task when it is small, which Spark decides by size."""
    width = len(basis.first().v)
    joined = attrs.join(basis, "attr")
    return joined.groupBy("node_id").agg(F.array(*[F.sum(F.col("value") * F.col("v")[i]) for i in range(width)]).alias("y"))


def frequencies(k: int, delta: float = 1.0, seed: int = 1, kind: str = "orthogonal", bandwidth: str = "root", orientation: str = "rows") -> np.ndarray:
    """k x k matrix whose product with a row gives the angles of its random features.

    ``orthogonal``: a uniform rotation (QR with the signs of R's diagonal fixed) whose rows get the lengths of Gaussian rows; ``iid``:
    a Gaussian matrix. ``bandwidth='root'`` divides by the root of delta, which is unbiased for exp(x.y / delta); ``as_printed``
    divides by delta. ``orientation='rows'`` takes the scaled rows as frequencies, ``as_printed`` the columns.
    """
    rng = np.random.default_rng(seed)
    m = rng.standard_normal((k, k))
    if kind == "orthogonal":
        q, r = np.linalg.qr(m)
        m = np.sqrt(rng.chisquare(k, k))[:, None] * (q * np.sign(np.diag(r)))
    m = m / (np.sqrt(delta) if bandwidth == "root" else delta)
    return m.T if orientation == "rows" else m


def random_features(y: np.ndarray, m: np.ndarray, delta: float = 1.0, scale: str = "normalized", unit_rows: bool = False) -> np.ndarray:
    """Sines and cosines of y's angles; their inner products estimate exp(x.y / delta) of unit rows.

    ``as_printed`` scaling doubles that (a constant that normalisation removes). ``unit_rows`` allows for rows that
    truncation has shortened.
    """
    angles = y @ m
    factor = np.sqrt((2.0 if scale == "as_printed" else 1.0) * np.exp(1 / delta) / m.shape[1])
    if unit_rows:
        factor = factor * np.exp(((y * y).sum(axis=1, keepdims=True) - 1) / (2 * delta))
    return factor * np.concatenate([np.sin(angles), np.cos(angles)], axis=1)


def _features(frames: Iterator[pd.DataFrame], m: np.ndarray, options: dict) -> Iterator[pd.DataFrame]:
    for pdf in frames:
        if len(pdf):
            yield pd.DataFrame({"node_id": pdf["node_id"], "y": list(random_features(np.stack(pdf["y"].to_numpy()), m, **options))})


def normalize(rows: DataFrame, nonneg: str = "clip") -> DataFrame:
    """(node_id, z): y over the root of its dot product with the sum of all rows.

    Where that product isn't positive (signed attributes, or a random-feature estimate), ``clip`` gives a zero row, ``drop``
    leaves the row out and ``error`` raises.
    """
    # a row a place of the vector, as many as there are factors
    sums = rows.select(F.posexplode("y").alias("place", "x")).groupBy("place").agg(F.sum("x").alias("s")).collect()
    if not sums:
        return rows.select("node_id", F.col("y").alias("z"))
    both = rows.withColumn("p", vec_dot("y", F.lit([float(r.s) for r in sorted(sums)])))
    if nonneg == "drop":
        both = both.where("p > 0")
    bad = F.raise_error(F.lit("a row sum isn't positive")).cast("double") if nonneg == "error" else F.lit(0.0)
    return both.select("node_id", vec_scale("y", F.when(F.col("p") > 0, 1 / F.sqrt("p")).otherwise(bad)).alias("z"))


def build(
    attrs: DataFrame, kernel: str = "cosine", k: int | None = 32, delta: float = 1.0, method: str = "gram", seed: int = 1,
    features: str = "orthogonal", nonneg: str = "clip", **options,
) -> DataFrame:
    """Factor table of unit attribute rows; k=None keeps every attribute (no truncation, the exact cosine affinity)."""
    if k is None:
        from attrgraph.operators.attributes import as_vectors

        y = as_vectors(attrs).select("node_id", F.col("x").alias("y"))
    else:
        basis, _ = truncated_svd(attrs, k, method, seed=seed)
        y = project(attrs, basis)
    if kernel == "expcos":
        workers(attrs.sparkSession)
        y = materialise(y, "rows")
        width = len(y.first().y)
        chosen = {n: options[n] for n in ("bandwidth", "orientation") if n in options}
        m = frequencies(width, delta, seed, features, **chosen)
        rest = {"delta": delta} | {n: options[n] for n in ("scale", "unit_rows") if n in options}
        y = y.mapInPandas(partial(_features, m=m, options=rest), "node_id long, y array<double>")
    elif kernel != "cosine":
        raise ValueError(f"no kernel {kernel}")
    return normalize(materialise(y, "rows"), nonneg)
