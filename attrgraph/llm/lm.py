"""Masked pseudo-likelihood scoring by a bidirectional window network.

Every word is predicted from the two words on each side. The network (numpy) maps those four words' classes to a hidden
layer and to a distribution over word classes: the commonest words of the corpus stand alone, the others share a class
by the hash of their last bytes. Within a class, a word's probability is its own count's share of the class's count, over *all*
documents: the counts are a table that grows with the vocabulary and is joined in scoring. The network passes over the whole
texts of all documents. A document's score is the sum of its words' conditional log-probabilities.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator
from functools import partial

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from attrgraph.session import materialise, workers

FREQUENT = 48
SUFFIX_CLASSES = 80
CLASSES = FREQUENT + SUFFIX_CLASSES
BINS_PER_CLASS = 2**56  # a word's place in its class is 56 bits of its hash: its own number
SIDE = 2
HIDDEN = 32
START_DOCS = 600
HEAD_WORDS = 150_000
_MEMO_LIMIT = 150_000
_COUNTED_LIMIT = 300_000
_WIDTH = 65_536
_SUMMERS = 8
_SEED = 42  # of Spark's xxhash64
_OFFSETS = [o for o in range(-SIDE, SIDE + 1) if o]


class WordBins(dict):
    """Word -> class * BINS_PER_CLASS + the word's number (0 for a word that is its own class)."""

    def __init__(self, frequent: list[bytes]):
        self.frequent = {w: i for i, w in enumerate(frequent)}
        self.kinds: dict[bytes, int] = {}

    def __missing__(self, word: bytes) -> int:
        if len(self) >= _MEMO_LIMIT:
            self.clear()
        own = self.frequent.get(word)
        if own is None:
            kind = self.kinds.get(word[-2:])
            if kind is None:
                kind = self.kinds[word[-2:]] = FREQUENT + (xxhash.xxh64_intdigest(word[-2:], _SEED) >> 1) % SUFFIX_CLASSES
            value = kind * BINS_PER_CLASS + xxhash.xxh64_intdigest(word, _SEED) % BINS_PER_CLASS
        else:
            value = own * BINS_PER_CLASS
        self[word] = value
        return value

    def of(self, text: bytes | None) -> np.ndarray:
        words = (text or b"").lower().split()
        return np.fromiter(map(self.__getitem__, words), np.int64, len(words))


class WordKinds(dict):
    """Last two bytes of a word -> its class as in ``WordBins``, for passes that need no number: a rare word costs no hash of its own."""

    def __init__(self, frequent: list[bytes]):
        self.frequent = {w: i for i, w in enumerate(frequent)}

    def __missing__(self, end: bytes) -> int:
        value = self[end] = FREQUENT + (xxhash.xxh64_intdigest(end, _SEED) >> 1) % SUFFIX_CLASSES
        return value

    def of(self, text: bytes | None) -> np.ndarray:
        own = self.frequent
        return np.array([own[w] if w in own else self[w[-2:]] for w in (text or b"").lower().split()], np.int32)


def contexts(sizes: np.ndarray, kinds: np.ndarray) -> np.ndarray:
    """Classes at the offsets around each word, CLASSES beyond a document's ends."""
    apart = np.full(len(kinds) + SIDE * (len(sizes) + 1), CLASSES, np.int32)
    at = np.arange(len(kinds)) + np.repeat(SIDE * np.arange(1, len(sizes) + 1), sizes)
    apart[at] = kinds
    return np.stack([apart[at + o] for o in _OFFSETS], axis=1)


WEIGHTS = ("inputs", "bias", "out", "out_bias")


class WindowNetwork:
    """One hidden layer over a table of input vectors for each offset."""

    def __init__(self, seed: int = 3):
        rng = np.random.default_rng(seed)
        self.inputs = (rng.standard_normal((len(_OFFSETS), CLASSES + 1, HIDDEN)) * 0.2).astype(np.float32)
        self.bias = np.zeros(HIDDEN, np.float32)
        self.out = (rng.standard_normal((HIDDEN, CLASSES)) * 0.1).astype(np.float32)
        self.out_bias = np.zeros(CLASSES, np.float32)
        self.squares = {name: np.full(getattr(self, name).shape, 1e-2, np.float32) for name in WEIGHTS}

    def hidden(self, around: np.ndarray) -> np.ndarray:
        h = self.bias + self.inputs[0][around[:, 0]]
        for k in range(1, len(_OFFSETS)):
            h += self.inputs[k][around[:, k]]
        return np.tanh(h, out=h)

    def log_prob(self, around: np.ndarray, target: np.ndarray) -> np.ndarray:
        z = self.hidden(around) @ self.out
        z += self.out_bias
        chosen = z[np.arange(len(z)), target].astype(np.float64)
        np.exp(z, out=z)  # tanh bounds the sums, so no shift is needed for float32
        return chosen - np.log((z @ np.ones(CLASSES, np.float32)).astype(np.float64))

    def fit(self, around: np.ndarray, target: np.ndarray, epochs: int = 3, batch: int = 512, rate: float = 0.2) -> None:
        """Adagrad on the negative log-probability; its sums of squares stay with the network."""
        rng = np.random.default_rng(5)

        def step(name: str, g: np.ndarray) -> None:
            self.squares[name] += g * g
            getattr(self, name)[...] -= rate * g / np.sqrt(self.squares[name])

        for _ in range(epochs if len(target) else 0):
            order = rng.permutation(len(target))
            for i in range(0, len(order), batch):
                pick = order[i : i + batch]
                a, t = around[pick], target[pick]
                h = self.hidden(a)
                z = h @ self.out
                z += self.out_bias
                np.exp(z, out=z)  # no shift, as in log_prob
                ones = np.ones(len(t), np.float32)
                z *= (1 / (z @ np.ones(CLASSES, np.float32) * len(t)))[:, None]
                z[np.arange(len(t)), t] -= np.float32(1 / len(t))
                dh = z @ self.out.T
                dh *= 1 - h * h
                step("out", h.T @ z)
                step("out_bias", ones @ z)
                g = np.zeros_like(self.inputs)
                for k in range(len(_OFFSETS)):
                    rank = np.argsort(a[:, k].astype(np.int16), kind="stable")
                    runs = a[rank, k]
                    first = np.flatnonzero(np.concatenate([[True], runs[1:] != runs[:-1]]))
                    g[k][runs[first]] = np.add.reduceat(dh[rank], first, axis=0)
                step("inputs", g)
                step("bias", ones @ dh)
            np.clip(self.out, -2, 2, out=self.out)


def _count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    counts: Counter[bytes] = Counter()

    def packed() -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(list(counts), pa.binary()), pa.array(list(counts.values()), pa.int64())], ["word", "n"])

    for batch in batches:
        for t in batch.column(0).cast(pa.binary()):
            counts.update((t.as_py() or b"").lower().split())
            if len(counts) >= _COUNTED_LIMIT:
                yield packed()
                counts.clear()
    yield packed()


def word_counts(docs: DataFrame) -> DataFrame:
    """(word, id, n): every word of all documents, its number as in ``WordBins`` without frequent words, and its count."""
    counted = docs.select("text").mapInArrow(_count, "word binary, n long").groupBy("word").agg(F.sum("n").alias("n"))
    kind = F.shiftrightunsigned(F.xxhash64(F.expr("substring(word, -2)")), 1) % SUFFIX_CLASSES + FREQUENT
    number = F.shiftleft(kind, 56).bitwiseOR(F.xxhash64("word").bitwiseAND(F.lit(BINS_PER_CLASS - 1)))
    return materialise(counted.select("word", number.alias("id"), "n"), "words")


def frequent_words(counts: DataFrame) -> list[bytes]:
    return [bytes(r.word) for r in counts.orderBy(F.desc("n"), "word").limit(FREQUENT).collect()]


def _others(counts: DataFrame, frequent: list[bytes]) -> DataFrame:
    return counts.where(~F.col("word").isin(frequent)) if frequent else counts


def _class_totals(counts: DataFrame, frequent: list[bytes]) -> np.ndarray:
    """Occurrences of each shared class; 1 for words of their own class, whose share is one, and for empty classes."""
    total = np.ones(CLASSES)
    for r in _others(counts, frequent).groupBy(F.shiftright("id", 56).alias("kind")).agg(F.sum("n").alias("n")).collect():
        total[r.kind] = r.n
    return total


class Shares:
    """log(count of a word / count of its class) by the word's number; a slice takes all numbers in its range."""

    def __init__(self, ids: np.ndarray, logs: np.ndarray):
        order = np.argsort(ids)
        self.ids, self.logs = ids[order], logs[order]

    def __getitem__(self, key):
        if isinstance(key, slice):
            lo = 0 if key.start is None else np.searchsorted(self.ids, key.start)
            return self.logs[lo : None if key.stop is None else np.searchsorted(self.ids, key.stop)]
        at = np.searchsorted(self.ids, key)
        inside = np.minimum(at, len(self.ids) - 1)
        return np.where(self.ids[inside] == key, self.logs[inside], -np.inf)


def corpus_shares(docs: DataFrame, frequent: list[bytes]) -> Shares:
    """The exact shares of all words on the driver: for small tables, scoring joins them instead."""
    counts = word_counts(docs)
    total = _class_totals(counts, frequent)
    held = _others(counts, frequent).select("id", "n").toPandas()
    ids, n = held["id"].to_numpy(np.int64), held["n"].to_numpy(np.float64)
    own = np.arange(len(frequent), dtype=np.int64) * BINS_PER_CLASS
    return Shares(np.concatenate([own, ids]), np.concatenate([np.zeros(len(own)), np.log(n / total[ids >> 56])]))


def _learn(batches: Iterator[pa.RecordBatch], frequent: list[bytes], net: WindowNetwork, epochs: int, batch: int) -> Iterator[pa.RecordBatch]:
    """A pass over whole texts: (words learnt from, weights and sums of squares as one float32 array)."""
    classes, held, width, words = WordKinds(frequent), [], 0, 0

    def fit() -> None:
        kinds = np.concatenate(held)
        net.fit(contexts(np.array([len(x) for x in held], np.int64), kinds), kinds, epochs, batch)

    for some in batches:
        for t in some.column(0).cast(pa.binary()):
            held.append(classes.of(t.as_py()))
            width += len(held[-1])
            if epochs == 1 and width > _WIDTH:
                fit()
                words, held, width = words + width, [], 0
    if width:
        fit()
    if words + width:
        yield _packed(words + width, np.concatenate([x.ravel() for x in _parts(net)]))


def _parts(net: WindowNetwork) -> list[np.ndarray]:
    return [getattr(net, name) for name in WEIGHTS] + [net.squares[name] for name in WEIGHTS]


def _packed(words: int, flat: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([words], pa.int64()), pa.array([flat.astype(np.float64).tobytes()], pa.binary())], ["words", "weights"])


def _average(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """One row: the mean of networks, weighted by their words."""
    words, total = 0, None
    for batch in batches:
        for n, w in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
            part = np.frombuffer(w) * n
            words, total = words + n, part if total is None else total + part
    if words:
        yield _packed(words, total / words)


def _pass(rows: DataFrame, frequent: list[bytes], net: WindowNetwork, epochs: int, batch: int) -> WindowNetwork:
    """The mean of the networks that each partition learns from ``net`` on; they are summed by few tasks, then here."""
    made = rows.select("text").mapInArrow(partial(_learn, frequent=frequent, net=net, epochs=epochs, batch=batch), "words long, weights binary")
    parts = made.repartition(_SUMMERS).mapInArrow(_average, "words long, weights binary").collect()
    words = sum(r.words for r in parts)
    if not words:
        return net
    flat = sum(np.frombuffer(r.weights) * (r.words / words) for r in sorted(parts, key=lambda r: bytes(r.weights)))
    out, at = WindowNetwork(), 0
    for x in _parts(out):
        x[...] = flat[at : at + x.size].reshape(x.shape)
        at += x.size
    return out


def train(docs: DataFrame, start_docs: int = START_DOCS, counts: DataFrame | None = None) -> tuple[list[bytes], WindowNetwork]:
    """The commonest words of the corpus, and the network.

    One task gives a common starting point by three passes over the ``start_docs`` documents with the smallest hash of doc_id. From there
    each partition passes over the whole texts of all its documents, and the networks are averaged by their words.
    """
    frequent = frequent_words(word_counts(docs) if counts is None else counts)
    keys = docs.where("doc_id is not null and text is not null").select("doc_id").orderBy(F.xxhash64("doc_id"), "doc_id").limit(start_docs).collect()
    ids = sorted({r.doc_id for r in keys})
    net = WindowNetwork()
    if ids:
        net = _pass(docs.where(F.col("doc_id").isin(ids)).repartition(1).sortWithinPartitions("doc_id", "text"), frequent, net, 3, 512)
    return frequent, _pass(docs, frequent, net, 1, 2048)


def _score(batches: Iterator[pa.RecordBatch], frequent: list[bytes], net: WindowNetwork, class_log: np.ndarray, head: Shares) -> Iterator[pa.RecordBatch]:
    """Log-probabilities but for the counts of rare words, whose numbers are listed."""
    bins = WordBins(frequent)
    for batch in batches:
        sums, counts, rare, rare_sizes, held, width = [], [], [], [], [], 0

        def flush() -> None:
            sizes = np.array([len(x) for x in held], np.int64)
            flat = np.concatenate(held) if held else np.empty(0, np.int64)
            kinds = (flat >> 56).astype(np.int32)
            around, value = contexts(sizes, kinds), -class_log[kinds]
            for i in range(0, len(flat), 8192):
                value[i : i + 8192] += net.log_prob(around[i : i + 8192], kinds[i : i + 8192])
            shared = np.flatnonzero(kinds >= FREQUENT)
            logs = head[flat[shared]] if len(head.ids) else np.full(len(shared), -np.inf)
            known = np.isfinite(logs)
            value[shared[known]] += logs[known]
            far = np.zeros(len(flat) + 1, np.int64)
            far[shared[~known] + 1] = 1
            ends, running, listed = np.cumsum(sizes), np.concatenate([[0.0], np.cumsum(value)]), np.cumsum(far)
            sums.extend((running[ends] - running[ends - sizes]).tolist())
            counts.extend(sizes.tolist())
            rare.append(flat[shared[~known]])
            rare_sizes.append(listed[ends] - listed[ends - sizes])

        for t in batch.column(1).cast(pa.binary()):
            held.append(bins.of(t.as_py()))
            width += len(held[-1])
            if width > _WIDTH:
                flush()
                held, width = [], 0
        flush()
        ends = np.concatenate([[0], np.cumsum(np.concatenate(rare_sizes))])
        lists = pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(np.concatenate(rare), pa.int64()))
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(counts, pa.int64()), pa.array(sums, pa.float64()), lists], ["doc_id", "n_tokens", "part", "rare"])


def _head(counts: DataFrame, most: int) -> Shares:
    """log(count) of the commonest words: all words that are as common as a count that at most ``most`` words reach."""
    sizes = sorted(((r.n, r["count"]) for r in counts.groupBy("n").count().collect()), reverse=True)
    reached = np.cumsum([c for _, c in sizes])
    fits = int(np.searchsorted(reached, most, side="right"))
    if not fits:
        return Shares(np.empty(0, np.int64), np.empty(0))
    held = counts.where(F.col("n") >= sizes[fits - 1][0]).select("id", "n").toPandas()
    return Shares(held["id"].to_numpy(np.int64), np.log(held["n"].to_numpy(np.float64)))


def score_documents(docs: DataFrame, start_docs: int = START_DOCS, head_words: int = HEAD_WORDS) -> DataFrame:
    """doc_id, n_tokens, log_prob (sum over the words of the whole text) and mean_log_prob of every row.

    Words are runs of anything but ASCII white space, lower-cased in A-Z. Null texts, empty ones and those of white space have no
    words: sum and mean are 0. Rows with null doc_ids are scored and learnt from like others; repeated rows are counted and scored
    as often as they occur; other columns are ignored; an empty table gives an empty result. The counts of the ``head_words``
    commonest words are sent to the workers, those of all others are joined.
    """
    workers(docs.sparkSession)
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    counts = word_counts(rows)
    frequent, net = train(rows, start_docs, counts)
    others = _others(counts, frequent)
    run = partial(_score, frequent=frequent, net=net, class_log=np.log(_class_totals(counts, frequent)), head=_head(others, head_words))
    scored = rows.mapInArrow(run, "doc_id long, n_tokens long, part double, rare array<long>")
    scored = materialise(scored.withColumn("row", F.monotonically_increasing_id()), "scored")
    rare = scored.select("row", F.explode("rare").alias("id")).join(others.select("id", F.log("n").alias("log_n")), "id").groupBy("row").agg(F.sum("log_n").alias("rest"))
    total = F.col("part") + F.coalesce("rest", F.lit(0.0))
    return scored.drop("rare").join(rare, "row", "left").select("doc_id", "n_tokens", total.alias("log_prob"), (total / F.greatest("n_tokens", F.lit(1))).alias("mean_log_prob"))
