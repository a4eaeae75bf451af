"""Near-duplicate detection by MinHash with tensored banding.

Every distinct shingle set gets two small collections of sub-keys (each sub-key hashes a few
minhashes). A table key is one sub-key of the first collection combined with one of the second, so
``m + m`` sub-keys stand for ``m * m`` tables. A sub-key that only one set has can't be in a shared
table, so those go before any table key is formed.

Within a bucket, members are compared with one pivot. Members outside the bucket's largest component are then the bucket's
ends: a few rounds compare ends with a pivot of their own. What is still apart goes through an exact prefix filter: two sets of
that similarity must share one of each other's rarest shingles, early enough for the rest to suffice. So each pair across
components of a bucket is either ruled out exactly or confirmed on the full shingle sets. A pair at similarity 0.75
shares no table with probability 2 * (1 - 0.75^2)^10 = 0.05 %.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from attrgraph.session import discard, lean, materialise, workers

SHINGLE_WORDS = 5
THRESHOLD_PERCENT = 75
SUBKEYS = 10
ROWS = 2
#: Rounds of pivots among the ends; they save work and decide nothing, as the prefix filter leaves no pair out.
END_ROUNDS = 4
#: Rows that share a join key in one task: a pivot's pairs, a shingle's sets.
BLOCK_ROWS = 256
_MEMO_LIMIT = 150_000
_M1, _M2, _STEP = np.uint64(0xFF51AFD7ED558CCD), np.uint64(0xC4CEB9FE1A85EC53), np.uint64(0x9E3779B97F4A7C15)


class WordHashes(dict):
    """Word -> 64-bit hash; forgets everything when it has grown to its limit."""

    def __missing__(self, word: bytes) -> int:
        if len(self) >= _MEMO_LIMIT:
            self.clear()
        value = self[word] = xxhash.xxh3_64_intdigest(word)
        return value


def mix(x: np.ndarray) -> np.ndarray:
    """Finalise 64-bit hashes (public murmur3 constants)."""
    x = x ^ (x >> np.uint64(33))
    x = x * _M1
    x ^= x >> np.uint64(33)
    x = x * _M2
    return x ^ (x >> np.uint64(33))


def shingle_set(text: bytes | None, memo: WordHashes, words: int = SHINGLE_WORDS) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the word shingles of a UTF-8 text."""
    tokens = (text or b"").lower().split()
    n = len(tokens)
    if not n:
        return np.empty(0, np.uint64)
    width = min(words, n)
    hashes = np.fromiter(map(memo.__getitem__, tokens), np.uint64, n)
    out = hashes[: n - width + 1] + np.uint64(width)
    for k in range(1, width):
        out = out * _STEP + hashes[k : n - width + 1 + k]
    return np.unique(mix(out))


def _parameters(count: int) -> tuple[np.ndarray, np.ndarray]:
    seeds = mix(np.arange(1, 2 * count + 1, dtype=np.uint64) * _STEP)
    return seeds[:count] | np.uint64(1), seeds[count:]


def minhashes(shingles: np.ndarray, count: int) -> np.ndarray:
    factor, offset = _parameters(count)
    best = np.full(count, np.iinfo(np.uint64).max, np.uint64)
    for i in range(0, len(shingles), 4096):
        block = shingles[None, i : i + 4096] ^ offset[:, None]
        np.minimum(best, (block * factor[:, None]).min(axis=1), out=best)
    return best


def subkeys(values: np.ndarray, per_side: int = SUBKEYS, rows: int = ROWS) -> np.ndarray:
    """2 * per_side signed keys of minhashes; the first half is one collection, the second the other."""
    values = values.reshape(2 * per_side, rows)
    out = np.arange(1, 2 * per_side + 1, dtype=np.uint64) * _M1
    for k in range(rows):
        out = mix(out * _STEP + values[:, k])
    return out.view(np.int64)


def _sketch(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    memo = WordHashes()
    for batch in batches:
        sizes, first, second, keys = [], [], [], []
        for text in batch.column(1).cast(pa.binary()):
            s = shingle_set(text.as_py(), memo)
            sizes.append(len(s))
            first.append(int(s.sum(dtype=np.uint64).astype(np.int64)) if len(s) else 0)
            second.append(int(np.bitwise_xor.reduce(mix(s + _STEP)).astype(np.int64)) if len(s) else 0)
            keys.append(subkeys(minhashes(s, 2 * SUBKEYS * ROWS)) if len(s) else None)
        yield pa.RecordBatch.from_arrays(
            [batch.column(0), pa.array(sizes, pa.int64()), pa.array(first, pa.int64()), pa.array(second, pa.int64()), pa.array(keys, pa.list_(pa.int64()))],
            ["doc_id", "n_shingles", "sum_hash", "xor_hash", "keys"],
        )


def _sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    memo = WordHashes()
    for batch in batches:
        sets = [shingle_set(t.as_py(), memo).view(np.int64) for t in batch.column(1).cast(pa.binary())]
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(sets, pa.list_(pa.int64()))], ["id", "shingles"])


def components(edges: DataFrame) -> DataFrame:
    """(id, component_id = smallest id reachable) for undirected edges (a, b), by alternating stars.

    Nodes without an edge don't occur. Lineage is cut in each round; nothing but two counts per round
    comes to the driver.
    """
    current = materialise(edges.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u != v").distinct(), "edges")
    state = None
    while True:
        both = current.union(current.select(F.col("v"), F.col("u")).toDF("u", "v"))
        low = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.join(low, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u != v").distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low, "u").select(F.explode(F.array(F.struct("u", "m"), F.struct(F.col("v").alias("u"), "m"))).alias("e"))
        after = materialise(small.select("e.u", F.col("e.m").alias("v")).where("u != v").distinct(), "edges")
        n, total = after.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        discard(current)
        current = after
        if (n, total) == state or not n:
            break
        state = (n, total)
    return current.select(F.col("u").alias("id"), F.col("v").alias("component_id")).union(current.select(F.col("v"), F.col("v")).distinct())


def _similarities(pairs: DataFrame, sets: DataFrame) -> DataFrame:
    """(a, b, common, union) of the full shingle sets of (a, b).

    A pivot ``a`` of many pairs is dealt over blocks of its pairs, with a copy of its set for each.
    """
    busy = materialise(pairs.groupBy("a").agg(F.ceil(F.count("*") / BLOCK_ROWS).cast("int").alias("blocks")).where("blocks > 1"), "busy")
    placed = pairs.join(busy, "a", "left").withColumn("block", F.pmod(F.xxhash64("b"), F.coalesce("blocks", F.lit(1))).cast("int")).drop("blocks")
    joined = placed.join(sets.select(F.col("id").alias("b"), F.col("shingles").alias("sb")), "b")
    dealt = sets.join(busy.withColumnRenamed("a", "id"), "id", "left").select(F.col("id").alias("a"), F.col("shingles").alias("sa"), F.explode(F.sequence(F.lit(0), F.coalesce("blocks", F.lit(1)) - 1)).alias("block"))
    joined = joined.join(dealt, ["a", "block"])
    sized = joined.select("a", "b", F.size(F.array_intersect("sa", "sb")).alias("common"), (F.size("sa") + F.size("sb")).alias("both"))
    return sized.select("a", "b", "common", (F.col("both") - F.col("common")).alias("union"))


def _links(pairs: DataFrame, sets: DataFrame, similar: Column) -> DataFrame:
    """The pairs that are similar on full sets; of rows of one doc_id with several texts, one has to be."""
    return materialise(_similarities(pairs, sets).where(similar).select("a", "b").distinct(), "links")


def _possible_pairs(ends: DataFrame, members: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """(a, b): of ends (id) and members (id, component_id), the pairs across components that the prefix filter leaves.

    Each set's shingles are put in order, the rarest first. Sets of the wanted similarity share an element among the first
    n - ceil(percent n / 100) + 1 of each; and where the first shared one is, what follows must suffice for their overlap, which
    is at least percent / (100 + percent) of both sizes. Both hold for every such pair, so none is lost.
    """
    tall = sets.join(members.select("id"), "id", "left_semi").select("id", "sid", F.size("shingles").alias("n"), F.explode("shingles").alias("s"))
    shared = tall.groupBy("s").agg(F.count("*").cast("int").alias("df")).where("df > 1")
    ordered = tall.join(shared, "s").groupBy("sid", "id", "n").agg(F.sort_array(F.collect_list(F.struct("df", "s"))).alias("order"))
    need = F.ceil(F.col("n") * percent / 100)
    prefix = F.slice("order", 1, F.greatest(F.lit(0), F.size("order") - need + 1).cast("int"))
    rows = ordered.select("id", "n", (F.col("n") - F.size("order")).alias("alone"), F.posexplode(prefix).alias("k", "e"))
    rows = rows.select("id", "n", (F.col("n") - F.col("alone") - F.col("k")).alias("left"), "e.s", F.ceil(F.col("e.df") / BLOCK_ROWS).cast("int").alias("blocks"))
    rows = materialise(rows.join(members, "id").join(ends.select("id", F.lit(True).alias("end")), "id", "left"), "prefixes")
    one = rows.where("end").select("s", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("block"), *[F.col(c).alias(f"p_{c}") for c in ("id", "n", "left", "component_id")])
    two = rows.withColumn("block", F.pmod(F.xxhash64("id"), F.col("blocks")).cast("int"))
    enough = (100 + percent) * F.least("left", "p_left") >= percent * (F.col("n") + F.col("p_n"))
    found = one.join(two, ["s", "block"]).where((F.col("component_id") != F.col("p_component_id")) & enough & (F.col("end").isNull() | (F.col("id") < F.col("p_id"))))
    return found.select(F.least("id", "p_id").alias("a"), F.greatest("id", "p_id").alias("b")).distinct()


def near_duplicates(docs: DataFrame, percent: int = THRESHOLD_PERCENT) -> DataFrame:
    """One row per row of ``docs`` (doc_id, text): n_shingles, component_id, kept, and class_id of equal sets.

    Null or empty text, or text of white space only: no shingles, linked with nothing. Repeated rows are
    equal sets, so they share a class; rows of one doc_id with different texts count as one node. A row
    whose doc_id is null keeps its n_shingles, has a null component_id and kept = false. Other columns
    of ``docs`` are ignored. An empty table gives an empty result.
    """
    spark = workers(docs.sparkSession)
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    sketch = materialise(docs.mapInArrow(lean(_sketch, "minhash"), "doc_id long, n_shingles long, sum_hash long, xor_hash long, keys array<long>"), "sketch")
    signature = ["n_shingles", "sum_hash", "xor_hash"]
    real = sketch.where("n_shingles > 0 and doc_id is not null")
    classes = materialise(real.groupBy(*signature).agg(F.min("doc_id").alias("class_id"), F.min_by("keys", "doc_id").alias("keys")), "classes")

    each = classes.select("class_id", F.posexplode("keys").alias("slot", "key"))
    shared = each.groupBy("key").agg(F.count("*").alias("n")).where("n > 1").select("key")
    colliding = each.join(shared, "key").groupBy("class_id").agg(
        F.collect_list(F.when(F.col("slot") < SUBKEYS, F.col("key"))).alias("left"),
        F.collect_list(F.when(F.col("slot") >= SUBKEYS, F.col("key"))).alias("right"),
    )
    table_keys = F.transform("left", lambda x: F.transform("right", lambda y: F.xxhash64(x, y)))
    rows = materialise(colliding.where("size(left) > 0 and size(right) > 0").select(F.col("class_id").alias("id"), F.explode(F.array_distinct(F.flatten(table_keys))).alias("key")), "tables")
    # the pivot is the member in most tables: it is near the middle of its group, so most members are near it
    busy = rows.groupBy("id").agg(F.count("*").alias("n"))
    pivots = rows.join(busy, "id").groupBy("key").agg(F.max(F.struct("n", (-F.col("id")).alias("m"))).alias("top"), F.count("*").alias("size"))
    pivots = pivots.where("size > 1").select("key", (-F.col("top.m")).alias("pivot"))
    buckets = materialise(rows.join(pivots, "key"), "buckets")
    wanted = buckets.select("id").distinct()
    sets = docs.select("doc_id", "text").join(wanted.withColumnRenamed("id", "doc_id"), "doc_id", "left_semi")
    sets = materialise(sets.mapInArrow(lean(_sets, "minhash"), "id long, shingles array<long>").withColumn("sid", F.monotonically_increasing_id()), "sets")

    similar = 100 * F.col("common") >= percent * F.col("union")
    star = materialise(buckets.where("id != pivot").select(F.col("pivot").alias("a"), F.col("id").alias("b")).distinct(), "star")
    links = _links(star, sets, similar)
    members, checked, turn, few = buckets.select("key", "id"), star, 0, False
    while True:
        labels = components(links)
        placed = materialise(members.join(labels, "id", "left").withColumn("component_id", F.coalesce("component_id", "id")), "placed")
        mixed = placed.groupBy("key").agg(F.min("component_id").alias("lo"), F.max("component_id").alias("hi")).where("lo != hi").select("key")
        apart = materialise(placed.join(mixed, "key"), "apart")  # a bucket within one component stays so
        discard(placed)
        sizes = apart.groupBy("key", "component_id").agg(F.count("*").alias("n")).groupBy("key").agg(F.max_by("component_id", F.struct("n", "component_id")).alias("largest"))
        ends = materialise(apart.join(sizes, "key").where("component_id != largest").drop("largest"), "ends")
        nodes, members = apart.select("id", "component_id").distinct(), apart.select("key", "id")
        ids = ends.select("id").distinct()
        if few or turn == END_ROUNDS or ends.isEmpty():
            break
        busy = ends.groupBy("id").agg(F.count("*").alias("n"))
        pivots = ends.join(busy, "id").groupBy("key").agg(F.max(F.struct("n", "id", "component_id")).alias("top"))
        star = ends.join(pivots, "key").where("component_id != top.component_id").select(F.col("top.id").alias("a"), F.col("id").alias("b")).distinct()
        star = materialise(star.join(checked, ["a", "b"], "left_anti").join(checked.toDF("b", "a"), ["a", "b"], "left_anti"), "star")
        more = _links(star, sets, similar)
        links, checked, turn = links.union(more), checked.union(star), turn + 1
        few = 16 * more.count() <= ids.count()
    if not ends.isEmpty():
        more = _links(_possible_pairs(ids, nodes, sets, percent), sets, similar)
        if not more.isEmpty():
            labels = components(links.union(more))
    labels = materialise(labels, "labels")
    for done in (rows, buckets, sets):
        discard(done)
    labels = labels.select(F.col("id").alias("class_id"), "component_id")
    out = sketch.join(classes.select(*signature, "class_id").join(labels, "class_id", "left"), signature, "left")
    component = F.when(F.col("n_shingles") > 0, F.coalesce("component_id", "class_id")).otherwise(F.col("doc_id"))
    component = F.when(F.col("doc_id").isNotNull(), F.least(component, F.col("doc_id")))
    return out.select("doc_id", "n_shingles", component.alias("component_id"), F.coalesce(component == F.col("doc_id"), F.lit(False)).alias("kept"), "class_id")
