"""Benchmark decontamination with an FM-index for each shard of training text.

A shard is a run of documents of about ``SHARD_WORDS`` words (one document at least), as a sequence of numbers in the shard's own
vocabulary with a separator after each document. Its index has a suffix array (by prefix doubling of what is still tied), the
Burrows-Wheeler sequence in a wavelet matrix with ranks, and positions sampled along the text. It knows nothing of the
benchmark, so any number of benchmark blocks can be searched in it. All windows are searched backwards at once; occurrences
are located by stepping to a sampled position; the words they cover are merged into spans.
"""

from __future__ import annotations

import hashlib
import re
import uuid
from collections.abc import Iterator
from functools import partial

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from attrgraph.session import kept, lean, materialise, workers

WINDOW = 10
SAMPLE_EVERY = 8
BLOCK_CHARS = 16_000_000
SHARD_WORDS = 1 << 18
_TABLE = bytes(c + 32 if 65 <= c <= 90 else c if c >= 128 or 48 <= c <= 57 or 97 <= c <= 122 else 32 for c in range(256))
_WORD = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
_UPPER = str.maketrans({c: c + 32 for c in range(65, 91)})
_FOUND = "doc_id long, text_hash string, n_words long, hits array<struct<start:long,end:long>>, items array<string>"
_RESULT = "doc_id long, n_words long, n_hit long, n_items long, items_sha256 string, contaminated boolean, hits array<struct<start:long,end:long>>, items array<string>"


def words_of(text: bytes | None) -> list[bytes]:
    """ASCII-lower-cased words of a UTF-8 text."""
    return (text or b"").translate(_TABLE).split()


class Windows:
    """Distinct windows of benchmark items, by length, over word numbers from 1."""

    def __init__(self, items: list[tuple[str, str | None]], width: int = WINDOW):
        self.vocabulary: dict[bytes, int] = {}
        owners: dict[tuple[int, ...], set[str]] = {}
        for item, text in items:
            numbers = [self.vocabulary.setdefault(w, len(self.vocabulary) + 1) for w in words_of((text or "").encode())]
            size = min(width, len(numbers))
            for i in range(len(numbers) - size + 1 if size else 0):
                owners.setdefault(tuple(numbers[i : i + size]), set()).add(item)
        self.groups: list[tuple[int, np.ndarray, list[list[str]]]] = []
        for size in sorted({len(w) for w in owners}):
            mine = sorted(w for w in owners if len(w) == size)
            self.groups.append((size, np.array(mine, np.int64), [sorted(owners[w]) for w in mine]))


class _Numbers(dict):
    """Word -> its number from 1, in the order of first occurrence."""

    def __missing__(self, word: bytes) -> int:
        value = self[word] = len(self) + 1
        return value


class WaveletMatrix:
    """Rank and access over a sequence of small numbers, a level for each bit from the highest."""

    def __init__(self, sequence: np.ndarray, bits: int):
        self.levels: list[tuple[int, np.ndarray, int]] = []
        for b in reversed(range(bits)):
            bit = (sequence >> b & 1).astype(np.int8)
            ones = np.zeros(len(sequence) + 1, np.int32)
            np.cumsum(bit, out=ones[1:])
            self.levels.append((b, ones, len(sequence) - int(ones[-1])))
            sequence = np.concatenate([sequence[bit == 0], sequence[bit == 1]])

    def rank(self, symbol: np.ndarray, at: np.ndarray) -> np.ndarray:
        """How often each symbol occurs before each position."""
        start = np.zeros(len(at), np.int64)
        for b, ones, zeros in self.levels:
            one = (symbol >> b & 1) == 1
            start = np.where(one, zeros + ones[start], start - ones[start])
            at = np.where(one, zeros + ones[at], at - ones[at])
        return at - start

    def access(self, at: np.ndarray) -> np.ndarray:
        out = np.zeros(len(at), np.int64)
        for b, ones, zeros in self.levels:
            one = ones[at + 1] - ones[at]
            out |= one.astype(np.int64) << b
            at = np.where(one == 1, zeros + ones[at], at - ones[at])
        return out


def suffix_order(symbols: np.ndarray) -> np.ndarray:
    """Starts of the suffixes in their order, by prefix doubling; separators (0) all differ, so no comparison runs past one."""
    n = len(symbols)
    gaps = np.flatnonzero(symbols == 0)
    plain = symbols.astype(np.int64) + len(gaps)
    plain[gaps] = np.arange(len(gaps))
    bits = int(plain.max()).bit_length()
    width = max(1, min(3, 62 // max(1, bits)))
    key = plain.copy()
    for k in range(1, width):  # as many symbols as fit make the first key
        key <<= bits
        key[: n - k] |= plain[k:]
    places = np.arange(n)
    order = np.argsort(key)
    rank = np.empty(n, np.int64)
    found = key[order]
    while True:
        # equal keys stand together from ``places[first]`` on; that is their rank
        first = np.concatenate([[True], found[1:] != found[:-1]])
        rank[order[places]] = np.maximum.accumulate(np.where(first, places, 0))
        tied = ~(first & np.concatenate([first[1:], [True]]))
        places = places[tied]
        if not len(places):
            return order
        some = order[places]
        key = rank[some] * np.int64(n + 1) + rank[some + width]
        turn = np.argsort(key)
        order[places], found = some[turn], key[turn]
        width *= 2


class FMIndex:
    """Index of a sequence of symbols where 0 is a separator; the sequence must end with one."""

    def __init__(self, symbols: np.ndarray, every: int = SAMPLE_EVERY):
        n = len(symbols)
        suffixes = suffix_order(symbols)
        before = symbols[suffixes - 1]
        self.wavelet = WaveletMatrix(before.astype(np.int64), max(1, int(symbols.max(initial=0)).bit_length()))
        self.first = np.concatenate([[0], np.cumsum(np.bincount(symbols, minlength=int(symbols.max(initial=0)) + 1))])
        kept = (suffixes % every == 0) | (before == 0)
        self.is_kept, self.kept_before = kept, np.concatenate([[0], np.cumsum(kept)])
        self.positions = suffixes[kept]
        self.n = n

    def search(self, patterns: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(pattern, low, high) of the rows of patterns that occur: their suffixes are low..high-1."""
        alive = np.flatnonzero((patterns < len(self.first) - 1).all(axis=1))
        low, high = np.zeros(len(alive), np.int64), np.full(len(alive), self.n, np.int64)
        for k in reversed(range(patterns.shape[1])):
            symbol = patterns[alive, k]
            low = self.first[symbol] + self.wavelet.rank(symbol, low)
            high = self.first[symbol] + self.wavelet.rank(symbol, high)
            more = high > low
            alive, low, high = alive[more], low[more], high[more]
        return alive, low, high

    def locate(self, rows: np.ndarray) -> np.ndarray:
        out, steps = np.empty(len(rows), np.int64), 0
        left = np.arange(len(rows))
        while len(left):
            done = self.is_kept[rows]
            out[left[done]] = self.positions[self.kept_before[rows[done]]] + steps
            rows, left = rows[~done], left[~done]
            symbol = self.wavelet.access(rows)
            rows = self.first[symbol] + self.wavelet.rank(symbol, rows)
            steps += 1
        return out


class Shard:
    """The index of some documents' words, and where each document lies in it."""

    def __init__(self, texts: list[bytes | None]):
        self.vocabulary = _Numbers()
        number = self.vocabulary.__getitem__
        parts = [np.fromiter(map(number, words), np.int64, len(words)) for words in map(words_of, texts)]
        self.sizes = np.array([len(x) for x in parts], np.int64)
        self.starts = np.concatenate([[0], np.cumsum(self.sizes + 1)])
        gap = np.zeros(1, np.int64)
        self.index = FMIndex(np.concatenate([y for x in parts for y in (x, gap)])) if self.sizes.any() else None

    def find(self, windows: Windows) -> list[tuple[np.ndarray, set[str]]]:
        """For each document: (start, end) rows of merged hit words, and the items found."""
        out: list[tuple[np.ndarray, set[str]]] = [(np.empty((0, 2), np.int64), set()) for _ in self.sizes]
        if self.index is None:
            return out
        here = np.array([0, *[self.vocabulary.get(w, 0) for w in windows.vocabulary]], np.int64)
        delta = np.zeros(self.index.n + 1, np.int64)
        for size, patterns, owners in windows.groups:
            mine = here[patterns]
            known = np.flatnonzero((mine > 0).all(axis=1))
            which, low, high = self.index.search(mine[known])
            if not len(which):
                continue
            count = high - low
            rows = np.arange(int(count.sum())) - np.repeat(np.cumsum(count) - count - low, count)
            at = self.index.locate(rows)
            np.add.at(delta, at, 1)
            np.add.at(delta, at + size, -1)
            doc = np.searchsorted(self.starts, at, "right") - 1
            for d, w in np.unique(np.stack([doc, np.repeat(known[which], count)]), axis=1).T.tolist():
                out[d][1].update(owners[w])
        hit = np.cumsum(delta[:-1]) > 0
        edge = np.diff(np.concatenate([[0], hit.astype(np.int8), [0]]))
        spans = np.stack([np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)], axis=1)
        owner = np.searchsorted(self.starts, spans[:, 0], "right") - 1
        for d in np.unique(owner).tolist():
            out[d] = (spans[owner == d] - self.starts[d], out[d][1])
        return out


def shards(texts: list[bytes | None], most: int | None = None) -> Iterator[Shard]:
    """Indexes over the texts in turn; a shard is closed when its bytes could hold ``most`` words of some six bytes."""
    held, width = [], 0
    for t in texts:
        if held and width + len(t or b"") > 6 * (most or SHARD_WORDS):
            yield Shard(held)
            held, width = [], 0
        held.append(t)
        width += len(t or b"")
    if held:
        yield Shard(held)


_WINDOWS: dict[tuple, Windows] = kept("fmindex")


def _windows(key: tuple, items: list[tuple[str, str | None]], width: int) -> Windows:
    """The windows of a block, built once in each worker process."""
    if key not in _WINDOWS:
        _WINDOWS.clear()
        _WINDOWS[key] = Windows(items, width)
    return _WINDOWS[key]


def _blocks(benchmark: DataFrame, width: int, block_chars: int) -> Iterator[dict]:
    """The benchmark's items in blocks of about ``block_chars`` characters; one block at a time is on the driver."""
    items = benchmark.where("item_id is not null").select(F.col("item_id").cast("string").alias("item"), F.col("text").cast("string").alias("text"))
    blocks = int((items.agg(F.sum(F.length("text"))).first()[0] or 0) // block_chars) + 1
    name = uuid.uuid4().hex
    for b in range(blocks):
        some = items.where(F.pmod(F.xxhash64("item", "text"), F.lit(blocks)) == b) if blocks > 1 else items
        yield {"key": (name, b), "items": sorted((r.item, r.text or "") for r in some.collect()), "width": width, "blocks": blocks}


def _find(batches: Iterator[pa.RecordBatch], block: dict) -> Iterator[pa.RecordBatch]:
    windows = _windows(block["key"], block["items"], block["width"])
    for batch in batches:
        sizes, found = [], []
        for shard in shards([t.as_py() for t in batch.column(2).cast(pa.binary())]):
            sizes.append(shard.sizes)
            found += shard.find(windows)
        hits = [[{"start": int(a), "end": int(b)} for a, b in spans] for spans, _ in found]
        n_words = pa.array(np.concatenate(sizes) if sizes else [], pa.int64())
        columns = [batch.column(0), batch.column(1), n_words, pa.array(hits, pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))), pa.array([sorted(i) for _, i in found], pa.list_(pa.string()))]
        yield pa.RecordBatch.from_arrays(columns, ["doc_id", "text_hash", "n_words", "hits", "items"])


def merge_spans(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """Sorted spans with those that overlap or touch made one."""
    out: list[tuple[int, int]] = []
    for a, b in sorted(spans):
        if out and a <= out[-1][1]:
            out[-1] = (out[-1][0], max(b, out[-1][1]))
        else:
            out.append((a, b))
    return out


def _digest(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    for pdf in frames:
        hits = [merge_spans([(s["start"], s["end"]) for s in h]) for h in pdf["hits"]]
        items = [sorted(set(i)) for i in pdf["items"]]
        n_hit = [sum(b - a for a, b in h) for h in hits]
        yield pd.DataFrame({
            "doc_id": pdf["doc_id"].astype("Int64"), "n_words": pdf["n_words"], "n_hit": n_hit, "n_items": [len(i) for i in items],
            "items_sha256": [hashlib.sha256(",".join(i).encode()).hexdigest() for i in items], "contaminated": [n > 0 for n in n_hit],
            "hits": [[{"start": a, "end": b} for a, b in h] for h in hits], "items": items,
        })


def find_contamination(docs: DataFrame, benchmark: DataFrame, width: int = WINDOW, block_chars: int = BLOCK_CHARS) -> DataFrame:
    """Which words of (doc_id, text) lie in windows of benchmark (item_id, text).

    Returns for each row doc_id, n_words, n_hit, n_items, items_sha256, contaminated, and the merged spans (word
    numbers) and items themselves. Null and empty texts have no words; items without words have no windows; items
    with a null item_id are left out; rows of one item_id count as one item. The benchmark is sent to the workers in
    blocks of about ``block_chars`` characters (one item at least), each searched in its own pass, and what several
    blocks find in a row is merged. Very long texts are indexed whole, as a shard of their own. Other columns are ignored;
    repeated rows give repeated results; an empty table gives an empty result.
    """
    workers(docs.sparkSession)
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.sha2(F.col("text").cast("string"), 256).alias("text_hash"), F.col("text").cast("string").alias("text"))
    found = None
    for block in _blocks(benchmark, width, block_chars):
        part = rows.mapInArrow(lean(partial(_find, block=block), "fmindex"), _FOUND)
        if block["blocks"] > 1:
            part = materialise(part, "found")
        found = part if found is None else found.union(part)
    if block["blocks"] > 1:
        found = found.groupBy("doc_id", "text_hash", "n_words").agg(F.flatten(F.collect_list("hits")).alias("hits"), F.flatten(F.collect_list("items")).alias("items"), (F.count("*") / block["blocks"]).cast("int").alias("copies"))
        found = found.withColumn("copies", F.explode(F.sequence(F.lit(1), "copies"))).drop("copies")
    return found.drop("text_hash").mapInPandas(_digest, _RESULT)


def cut_spans(text: str, hits: list[tuple[int, int]]) -> str:
    """The text without the stretches from each span's first word to its last; what is around stays as it is."""
    if not hits:
        return text
    words = list(_WORD.finditer(text.translate(_UPPER)))
    out, at = [], 0
    for a, b in hits:
        out.append(text[at : words[a].start()])
        at = words[b - 1].end()
    return "".join(out) + text[at:]


def _remove(batches: Iterator[pa.RecordBatch], block: dict) -> Iterator[pa.RecordBatch]:
    windows = _windows(block["key"], block["items"], block["width"])
    for batch in batches:
        column = batch.schema.get_field_index("text")
        texts = batch.column(column).to_pylist()
        rows = list(range(len(texts)))
        while rows:  # a cut may join words into another window
            changed, at = [], 0
            for shard in shards([texts[i].encode() if texts[i] else None for i in rows]):
                for spans, _ in shard.find(windows):
                    if len(spans):
                        texts[rows[at]] = cut_spans(texts[rows[at]], spans.tolist())
                        changed.append(rows[at])
                    at += 1
            rows = changed
        yield batch.set_column(column, batch.schema.field(column), pa.array(texts, batch.schema.field(column).type))


def _cut(batches: Iterator[pa.RecordBatch], column: int) -> Iterator[pa.RecordBatch]:
    """Cuts the spans in the last column out of the texts; drops that column."""
    for batch in batches:
        hits = [merge_spans([(s["start"], s["end"]) for s in h or ()]) for h in batch.column(batch.num_columns - 1).to_pylist()]
        texts = [cut_spans(t, h) if h else t for t, h in zip(batch.column(column).to_pylist(), hits, strict=True)]
        field = batch.schema.field(column)
        plain = batch.select(range(batch.num_columns - 1))
        yield plain.set_column(column, field, pa.array(texts, field.type))


def remove_contamination(docs: DataFrame, benchmark: DataFrame, width: int = WINDOW, block_chars: int = BLOCK_CHARS) -> DataFrame:
    """``docs`` with its columns, where the hit spans are cut out of ``text``; no row goes.

    Spans of all windows are merged before they are cut, and what a cut joins into another window is cut in the next turn, until
    no window is left; so the result doesn't depend on how the benchmark falls into blocks. Null and empty texts stay as they
    are, and so do texts without a window; repeated rows and null doc_ids are treated like others, columns of any other name
    pass through; an empty table or an empty benchmark changes nothing.
    """
    workers(docs.sparkSession)
    blocks = _blocks(benchmark, width, block_chars)
    block = next(blocks)
    if block["blocks"] == 1:
        return docs.mapInArrow(lean(partial(_remove, block=block), "fmindex"), docs.schema)
    digest, spans = f"digest_{uuid.uuid4().hex}", f"hits_{uuid.uuid4().hex}"
    left = docs
    while True:
        texts = left.where("text is not null").select(F.lit(0).cast("long").alias("doc_id"), F.sha2("text", 256).alias("text_hash"), "text").dropDuplicates(["text_hash"])
        found = None
        for block in _blocks(benchmark, width, block_chars):
            part = materialise(texts.mapInArrow(lean(partial(_find, block=block), "fmindex"), _FOUND).where("size(hits) > 0").select("text_hash", "hits"), "found")
            found = part if found is None else found.union(part)
        if found.isEmpty():
            return left
        merged = found.groupBy(F.col("text_hash").alias(digest)).agg(F.flatten(F.collect_list("hits")).alias(spans))
        told = left.withColumn(digest, F.sha2("text", 256)).join(merged, digest, "left").select(*[F.col(f"`{c}`") for c in left.columns], spans)
        left = materialise(told.mapInArrow(lean(partial(_cut, column=left.columns.index("text")), "fmindex"), left.schema), "cut")
