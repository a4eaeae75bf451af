"""Graphs, attributes and truth of the given tables. Each returns pairs (a, b), attrs (node_id, attr, value) or
truth (node_id, label)."""

from __future__ import annotations

from collections.abc import Iterator
from functools import partial

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from attrgraph.functions import text_hash
from attrgraph.operators import sharing
from attrgraph.session import materialise, workers

TOKEN_BUCKETS = 2048


def co_occurrence(rows: DataFrame, key: Column | str, item: Column | str, min_support: int = 1, most: int | None = None) -> DataFrame:
    """Pairs of items that share at least ``min_support`` keys; keys with more than ``most`` items are no evidence.

    ``most`` is part of the graph's definition. Left out, every key counts, and a hot key's pairs are made by a join on the
    key and a salt, so no single task holds them.
    """
    held = rows.select(F.col(key).alias("k") if isinstance(key, str) else key.alias("k"), F.col(item).alias("i") if isinstance(item, str) else item.alias("i")).where("k is not null and i is not null").distinct()
    sizes = held.groupBy("k").agg(F.count("*").alias("n")).where(F.col("n") > 1)
    if most:
        sizes = sizes.where(F.col("n") <= most)
    held = held.join(sizes, "k")
    salts = F.greatest(F.lit(1), F.ceil(F.col("n") / 2000)).cast("int")
    left = held.withColumn("salt", F.pmod(F.xxhash64("i"), salts).cast("int")).select("k", "salt", F.col("i").alias("a"))
    right = held.select("k", F.explode(F.sequence(F.lit(0), salts - 1)).alias("salt"), F.col("i").alias("b"))
    pairs = left.join(right, ["k", "salt"]).where("a < b")
    return pairs.groupBy("a", "b").agg(F.count("*").alias("support")).where(F.col("support") >= min_support)


def copurchase(lineitem: DataFrame, min_support: int = 1) -> DataFrame:
    """Parts bought in one order."""
    return co_occurrence(lineitem, "l_orderkey", "l_partkey", min_support)


def customer_supplier(orders: DataFrame, lineitem: DataFrame, since: str = "2001-01-01") -> DataFrame:
    """Bipartite: customers (2 * key) and the suppliers (2 * key + 1) of their orders from ``since`` on."""
    recent = orders.where(F.col("o_orderdate") >= F.lit(since).cast("timestamp_ntz")).select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey")
    rows = lineitem.select("l_orderkey", "l_suppkey").join(recent, "l_orderkey")
    return rows.select((F.col("o_custkey") * 2).alias("a"), (F.col("l_suppkey") * 2 + 1).alias("b")).distinct()


def part_supplier(lineitem: DataFrame) -> DataFrame:
    """Bipartite: parts (2 * key) and suppliers (2 * key + 1) of one line."""
    return lineitem.select((F.col("l_partkey") * 2).alias("a"), (F.col("l_suppkey") * 2 + 1).alias("b")).distinct()


def _shared_lines(documents: DataFrame, longer_than: int) -> DataFrame:
    lines = documents.select("doc_id", F.explode(F.split("text", "\n")).alias("line")).select("doc_id", F.trim("line").alias("line"))
    return lines.where(F.length("line") > longer_than)


def document_overlap(documents: DataFrame, longer_than: int = 20, most: int | None = 50) -> DataFrame:
    """Documents that share a trimmed line of more than ``longer_than`` characters that at most ``most`` have; None for every line."""
    return co_occurrence(_shared_lines(documents, longer_than), F.md5("line"), "doc_id", 1, most)


def document_classes(documents: DataFrame, longer_than: int = 20) -> DataFrame:
    """``sharing.classes`` of the documents by their lines: the links of ``document_overlap`` with ``most`` None."""
    return sharing.classes(_shared_lines(documents, longer_than), F.md5("line"), "doc_id")


def document_links(documents: DataFrame, longer_than: int = 20) -> DataFrame:
    """Every shared line as a star: its smallest document and each other one. The components are those of
    ``document_overlap`` with ``most`` None, by as many pairs as there are memberships."""
    held = _shared_lines(documents, longer_than).where("doc_id is not null").select(F.md5("line").alias("k"), F.col("doc_id").alias("b")).distinct()
    return held.join(held.groupBy("k").agg(F.min("b").alias("a")), "k").where("a < b").select("a", "b").distinct()


def _bigrams(documents: DataFrame, words: int | None) -> DataFrame:
    w = F.filter(F.split(F.lower("text"), r"\s+"), lambda x: x != "")
    w = w if words is None else F.slice(w, 1, words)
    grams = F.zip_with(F.slice(F.col("w"), 1, F.size("w") - 1), F.slice(F.col("w"), 2, F.size("w") - 1), lambda x, y: F.concat_ws(" ", x, y))
    return documents.where("text is not null").select("doc_id", w.alias("w")).where(F.size("w") > 1).select("doc_id", F.explode(F.array_distinct(grams)).alias("g"))


def bigram_overlap(documents: DataFrame, words: int | None = 200, shared: int = 2, most: int | None = 6) -> DataFrame:
    """Documents that share ``shared`` bigrams of their first ``words`` words (split at white space) that at most ``most`` documents have.

    ``words`` None reads whole texts; the defaults define the small fixture graph. ``most`` None counts bigrams of every frequency, and the
    pairs are put out where they are found (``sharing``), without their support.
    """
    rows = _bigrams(documents, words)
    return co_occurrence(rows, "g", "doc_id", shared, most) if most else sharing.pairs(sharing.classes(rows, "g", "doc_id"), shared)


def coactivity(events: DataFrame, unit: str = "minute") -> DataFrame:
    """Users active in the same unit of time."""
    return co_occurrence(events, F.date_trunc(unit, F.col("ts")), "user_id")


def coactivity_graph(events: DataFrame, unit: str = "minute") -> sharing.SharedGraph:
    """The graph of ``coactivity``, whose pairs grow with the square of the users of a unit, without a table of them."""
    return sharing.SharedGraph(sharing.classes(events, F.date_trunc(unit, F.col("ts")), "user_id"))


def page_links(pages: DataFrame) -> DataFrame:
    """(page_id, href): distinct links of each page."""
    return pages.select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("href")).distinct()


def turn_paths(conversations: DataFrame) -> DataFrame:
    """Consecutive turns of a conversation; a turn's node is conv_id * 1000 + turn."""
    w = Window.partitionBy("conv_id").orderBy("turn")
    node = F.col("conv_id") * 1000 + F.col("turn")
    rows = conversations.select("conv_id", "turn").distinct().select(node.alias("a"), F.lead(node).over(w).alias("b"))
    return rows.where("b is not null")


def nation_tree(nation: DataFrame, customer: DataFrame) -> DataFrame:
    """Stars: region (negative ids from -1000), nation (from -100), customer."""
    up = nation.select((F.col("n_nationkey").cast("long") - 100).alias("a"), (F.col("n_regionkey").cast("long") - 1000).alias("b"))
    down = customer.select((F.col("c_nationkey").cast("long") - 100).alias("a"), F.col("c_custkey").alias("b"))
    return up.union(down)


def supplier_tree(nation: DataFrame, supplier: DataFrame) -> DataFrame:
    """A small tree: region (ids from -1000), nation (from -100), supplier."""
    down = supplier.select((F.col("s_nationkey").cast("long") - 100).alias("a"), F.col("s_suppkey").alias("b"))
    return nation.select((F.col("n_nationkey").cast("long") - 100).alias("a"), (F.col("n_regionkey").cast("long") - 1000).alias("b")).union(down)


def supplier_tree_attributes(nation: DataFrame, supplier: DataFrame) -> DataFrame:
    """Its nodes' region, nation and balance decile, as far as they have one."""
    n = nation.select("n_nationkey", "n_regionkey")
    s = supplier.join(n, F.col("s_nationkey") == F.col("n_nationkey"))
    decile = F.floor((F.col("s_acctbal") + 1000) / 1100).cast("string")
    place = lambda node: [node.alias("node_id"), F.col("n_nationkey").alias("nation"), F.col("n_regionkey").alias("region")]
    rows = s.select(*place(F.col("s_suppkey")), decile.alias("balance")).union(n.select(*place(F.col("n_nationkey").cast("long") - 100), F.lit(None).cast("string")))
    rows = rows.union(n.select((F.col("n_regionkey").cast("long") - 1000).alias("node_id"), F.lit(None).cast("int"), F.col("n_regionkey"), F.lit(None).cast("string")).distinct())
    return _one_hot(rows, "node_id", *[F.concat(F.lit(f"{k}:"), F.col(k).cast("string")) for k in ("nation", "region", "balance")])


def long_path(part: DataFrame, length: int = 120) -> DataFrame:
    """The ``length`` smallest part keys as a path."""
    first = part.select("p_partkey").orderBy("p_partkey").limit(length)
    w = Window.orderBy("p_partkey")
    return first.select(F.col("p_partkey").alias("a"), F.lead("p_partkey").over(w).alias("b")).where("b is not null")


def _nearest(dots: np.ndarray, ids: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """(ids, dots) of the k largest dots, ties to the smaller id."""
    if len(dots) > k:
        keep = np.flatnonzero(dots >= dots[np.argpartition(-dots, k - 1)[k - 1]])
        dots, ids = dots[keep], ids[keep]
    order = np.lexsort((ids, -dots))[:k]
    return ids[order], dots[order]


def _block_knn(frames: Iterator[pd.DataFrame], ids: np.ndarray, vectors: np.ndarray, k: int) -> Iterator[pd.DataFrame]:
    found: list[tuple[np.ndarray, np.ndarray]] = [(np.empty(0, np.int64), np.empty(0))] * len(ids)
    for pdf in frames:
        for lo in range(0, len(pdf), 4096):
            some = pdf.iloc[lo : lo + 4096]
            first, members, dots = some["row"].to_numpy(), some["members"].to_numpy(), np.stack(some["x"].to_numpy()) @ vectors.T
            for j, column in enumerate(np.ascontiguousarray(dots.T)):
                # of distinct rows the k nearest hold the k nearest of all, each with its smallest ids
                near = np.flatnonzero(np.isin(first, _nearest(column, first, k)[0]))
                sizes = [len(members[i]) for i in near]
                others, d = found[j]
                others, d = np.concatenate([others, *members[near]]), np.concatenate([d, np.repeat(column[near], sizes)])
                found[j] = _nearest(d, others, k)
    sizes = [len(x) for x, _ in found]
    if sum(sizes):
        yield pd.DataFrame({"q": np.repeat(ids, sizes), "other": np.concatenate([x for x, _ in found]), "dot": np.concatenate([d for _, d in found])})


def vector_knn(vectors: DataFrame, k: int = 10, block: int = 2048) -> DataFrame:
    """(q, other, dot, rank): exact K nearest by dot product, ties to the smaller id.

    Equal rows are one query, and one candidate with its k + 1 smallest ids. The queries are all distinct rows, sent to the workers in
    blocks; each task returns k + 1 rows a query. For large tables of distinct rows use the LSH route of ``embed.cluster_knn``.
    """
    spark = workers(vectors.sparkSession)
    rows = materialise(vectors.select("node_id", F.col("x").cast("array<double>").alias("x")), "vectors")
    kinds = rows.groupBy("x").agg(F.sort_array(F.collect_list("node_id")).alias("all"))
    kinds = materialise(kinds.select(F.col("all")[0].alias("row"), "x", F.slice("all", 1, k + 1).alias("members"), "all"), "distinct")
    pieces = max(1, -(-kinds.count() // block))
    dealt, found = kinds.select("row", "x", "members").repartition(spark.sparkContext.defaultParallelism, "row"), None
    for b in range(pieces):
        some = kinds.select("row", "x").where(F.pmod(F.xxhash64("row"), F.lit(pieces)) == b).toPandas()
        if not len(some):
            continue
        part = dealt.mapInPandas(partial(_block_knn, ids=some["row"].to_numpy(), vectors=np.stack(some["x"].to_numpy()), k=k + 1), "q long, other long, dot double")
        found = part if found is None else found.union(part)
    if found is None:
        return spark.createDataFrame([], "q long, other long, dot double, rank int")
    w = Window.partitionBy("q").orderBy(F.desc("dot"), "other")
    lists = found.withColumn("place", F.row_number().over(w)).where(F.col("place") <= k + 1).groupBy("q").agg(F.sort_array(F.collect_list(F.struct("place", "other", "dot"))).alias("near"))
    lists = materialise(lists, "lists").select(F.col("q").alias("row"), "near")
    # a row of each member, without itself
    near = kinds.select("row", F.explode("all").alias("q")).join(lists, "row").select("q", F.posexplode(F.slice(F.filter("near", lambda x: x["other"] != F.col("q")), 1, k)).alias("at", "x"))
    return near.select("q", "x.other", "x.dot", (F.col("at") + 1).alias("rank"))


def embedding_knn(embeddings: DataFrame, k: int = 10) -> DataFrame:
    """Vectors of which either is among the other's k nearest."""
    knn = vector_knn(embeddings.select(F.col("vec_id").alias("node_id"), F.col("embedding").alias("x")), k)
    return knn.select(F.least("q", "other").alias("a"), F.greatest("q", "other").alias("b")).distinct()


def _one_hot(rows: DataFrame, node: str, *features: Column) -> DataFrame:
    """attrs of equal value 1 for each feature string; a node's repeated feature counts once."""
    return rows.select(F.col(node).alias("node_id"), F.explode(F.array(*features)).alias("attr")).where("attr is not null").distinct().select("node_id", "attr", F.lit(1.0).alias("value"))


def part_attributes(part: DataFrame, brand: bool = True) -> DataFrame:
    words = F.split("p_name", " ")
    features = [F.concat(F.lit("size:"), F.floor((F.col("p_size") - 1) / 5).cast("string")), F.concat(F.lit("first:"), F.element_at(words, 1)), F.concat(F.lit("last:"), F.element_at(words, -1))]
    if brand:
        features.append(F.concat(F.lit("brand:"), F.col("p_brand")))
    return _one_hot(part, "p_partkey", *features)


def customer_attributes(customer: DataFrame, nation: DataFrame) -> DataFrame:
    rows = customer.join(F.broadcast(nation.select(F.col("n_nationkey").alias("c_nationkey"), "n_regionkey")), "c_nationkey", "left")
    decile = F.floor((F.col("c_acctbal") + 1000) / 1100).cast("string")
    return _one_hot(rows, "c_custkey", F.concat(F.lit("nation:"), F.col("c_nationkey").cast("string")), F.concat(F.lit("region:"), F.col("n_regionkey").cast("string")), F.concat(F.lit("balance:"), decile))


def document_attributes(documents: DataFrame, buckets: int = TOKEN_BUCKETS) -> DataFrame:
    """Counts of blank-split lower-case tokens in hashed buckets."""
    tokens = documents.select(F.col("doc_id").alias("node_id"), F.explode(F.split(F.lower("text"), " ")).alias("t")).where("t != ''")
    return tokens.groupBy("node_id", text_hash("t", buckets).cast("string").alias("attr")).agg(F.count("*").cast("double").alias("value"))


def page_attributes(pages: DataFrame, buckets: int = TOKEN_BUCKETS) -> DataFrame:
    text = F.regexp_replace("html", "<[^>]*>", " ")
    return document_attributes(pages.select(F.col("page_id").alias("doc_id"), text.alias("text")), buckets)


def user_attributes(events: DataFrame) -> DataFrame:
    """Histograms of event type and of the decile of props.k."""
    k = F.floor(F.get_json_object("props", "$.k").cast("int") / 10).cast("string")
    rows = events.select(F.col("user_id").alias("node_id"), F.explode(F.array(F.concat(F.lit("type:"), F.col("event_type")), F.concat(F.lit("k:"), k))).alias("attr"))
    return rows.where("attr is not null").groupBy("node_id", "attr").agg(F.count("*").cast("double").alias("value"))


def embedding_attributes(embeddings: DataFrame) -> DataFrame:
    return embeddings.select(F.col("vec_id").alias("node_id"), F.posexplode("embedding").alias("pos", "value")).select("node_id", F.col("pos").cast("string").alias("attr"), F.col("value").cast("double").alias("value"))


def truth_of(rows: DataFrame, node: str, label: str) -> DataFrame:
    return rows.where(F.col(label).isNotNull()).select(F.col(node).alias("node_id"), F.col(label).cast("string").alias("label"))
