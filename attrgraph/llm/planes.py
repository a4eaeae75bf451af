"""Token-id files made of bit planes.

A shard file holds the ids of consecutive documents. Ids are cut into chunks; a chunk's ids are written as
planes (plane k has bit k of every id, or byte k), each compressed with zstandard. The file ends with an index:

    "IDPLANE1" | planes of chunk 0 | planes of chunk 1 | ... | index | length of index (8 bytes) | "IDPLANE1"

The index, one zstandard frame of little-endian int64, holds: documents, chunks, kind (1: bits, 8: bytes); then for
each document its id, a null flag and its number of ids; then for each chunk its number of ids, its number of planes,
its offset in the file, and its planes' lengths.
"""

from __future__ import annotations

import os
import re
import uuid
import zlib
from collections.abc import Iterator
from functools import partial

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.fs
import zstandard as zstd
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from attrgraph.session import fresh_path, workers

MAGIC = b"IDPLANE1"
CHUNK_IDS = 1 << 16
MEMO_WORDS = 600_000


def pack(ids: np.ndarray, bits: int = 1) -> list[bytes]:
    """Planes of ``bits`` (1 or 8) of unsigned 32-bit ids, lowest first; as many as the largest id needs."""
    ids = np.ascontiguousarray(ids, "<u4")
    width = max(1, int(ids.max(initial=0)).bit_length())
    if bits == 8:
        table = ids.view(np.uint8).reshape(-1, 4)
        return [table[:, k].tobytes() for k in range(-(-width // 8))]
    return [np.packbits(((ids >> np.uint32(k)) & np.uint32(1)).astype(np.uint8), bitorder="little").tobytes() for k in range(width)]


def unpack(planes: list[bytes], n: int, bits: int = 1) -> np.ndarray:
    out = np.zeros(n, np.uint32)
    for k, plane in enumerate(planes):
        raw = np.frombuffer(plane, np.uint8)
        values = raw if bits == 8 else np.unpackbits(raw, count=n, bitorder="little")
        out |= values.astype(np.uint32) << np.uint32(k * bits)
    return out


class ShardWriter:
    """Writes one shard in one pass; the file gets its name when it is whole."""

    def __init__(self, folder: str, name: str, bits: int = 1, chunk_ids: int = CHUNK_IDS, level: int = 3):
        self.fs, root = pa.fs.FileSystem.from_uri(folder)
        self.path, self.part = f"{root}/{name}", f"{root}/.{name}.{uuid.uuid4().hex}"
        self.bits, self.chunk_ids, self.zip = bits, chunk_ids, zstd.ZstdCompressor(level=level)
        self.out = self.fs.open_output_stream(self.part)
        self.out.write(MAGIC)
        self.at, self.waiting, self.held = len(MAGIC), [], 0
        self.docs: list[tuple[int, int, int]] = []
        self.chunks: list[list[int]] = []
        self.total = 0

    def add(self, doc_id: int | None, ids: np.ndarray) -> None:
        self.docs.append((doc_id or 0, doc_id is None, len(ids)))
        self.waiting.append(ids)
        self.held += len(ids)
        self.total += len(ids)
        if self.held >= self.chunk_ids:
            self._flush(False)

    def _flush(self, last: bool) -> None:
        ids = np.concatenate(self.waiting) if self.waiting else np.empty(0, np.uint32)
        whole = len(ids) if last else len(ids) // self.chunk_ids * self.chunk_ids
        for i in range(0, whole, self.chunk_ids):
            block = ids[i : min(i + self.chunk_ids, whole)]
            planes = [self.zip.compress(p) for p in pack(block, self.bits)]
            self.chunks.append([len(block), len(planes), self.at, *map(len, planes)])
            for p in planes:
                self.out.write(p)
                self.at += len(p)
        self.waiting, self.held = [ids[whole:]], len(ids) - whole

    def close(self) -> None:
        self._flush(True)
        head = [len(self.docs), len(self.chunks), self.bits]
        index = np.concatenate([np.array(head, "<i8"), np.array(self.docs, "<i8").reshape(-1), *[np.array(c, "<i8") for c in self.chunks]])
        data = self.zip.compress(index.astype("<i8").tobytes())
        self.out.write(data + len(data).to_bytes(8, "little") + MAGIC)
        self.out.close()
        self.fs.move(self.part, self.path)


class ShardReader:
    """Reads a shard's index, and from it any chunk or the documents in order."""

    def __init__(self, uri: str):
        fs, path = pa.fs.FileSystem.from_uri(uri)
        self.file = fs.open_input_file(path)
        size = self.file.size()
        tail = self.file.read_at(len(MAGIC) + 8, size - len(MAGIC) - 8)
        if tail[8:] != MAGIC:
            raise ValueError(f"{uri} isn't a whole shard")
        n = int.from_bytes(tail[:8], "little")
        self.zip = zstd.ZstdDecompressor()
        index = np.frombuffer(self.zip.decompress(self.file.read_at(n, size - len(MAGIC) - 8 - n)), "<i8")
        n_docs, n_chunks, self.bits = (int(x) for x in index[:3])
        self.docs = index[3 : 3 + 3 * n_docs].reshape(-1, 3)
        self.chunks, at = [], 3 + 3 * n_docs
        for _ in range(n_chunks):
            count, planes, offset = (int(x) for x in index[at : at + 3])
            self.chunks.append((count, offset, [int(x) for x in index[at + 3 : at + 3 + planes]]))
            at += 3 + planes

    def chunk(self, k: int) -> np.ndarray:
        count, offset, sizes = self.chunks[k]
        raw, planes, at = self.file.read_at(sum(sizes), offset), [], 0
        for s in sizes:
            planes.append(self.zip.decompress(raw[at : at + s]))
            at += s
        return unpack(planes, count, self.bits)

    def documents(self) -> Iterator[tuple[int | None, np.ndarray]]:
        held, at = np.empty(0, np.uint32), 0
        chunks = iter(range(len(self.chunks)))
        for doc_id, null, n in self.docs.tolist():
            parts, have = [held[at:]], len(held) - at
            while have < n:
                held, at = self.chunk(next(chunks)), 0
                parts.append(held)
                have += len(held)
            if len(parts) > 1:
                held, at = np.concatenate(parts), 0
            yield None if null else doc_id, held[at : at + n]
            at += n


#: Characters whose classes no Unicode version changes (white space, ASCII, Latin letters, common punctuation, no
#: fractions or raised digits); other texts go to the tokenizer whole.
_PLAIN = re.compile(r"[\t\n\r\x20-\x7e¡-±´-¸º»¿-ɏ‐-‧]*\Z")
#: Fixed: the splitting rule of this byte-level family before merging, with the classes written out for those characters.
_LETTERS = "A-Za-zªµºÀ-ÖØ-öø-ɏ"
_SPLIT = re.compile(rf"'s|'t|'re|'ve|'m|'ll|'d| ?[{_LETTERS}]+| ?[0-9]+| ?[^\s0-9{_LETTERS}]+|\s+(?!\S)|\s+")


class ByteTokenizer:
    """A byte-level tokenizer file with a bounded memo of what its words encode to."""

    def __init__(self, path: str):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.model = Tokenizer.from_file(path)
        self.added = [t.content for t in self.model.get_added_tokens_decoder().values()]
        self.memo: dict[str, bytes] = {}

    def _whole(self, texts: list[str]) -> list[bytes]:
        return [np.array(e.ids, "<u4").tobytes() for e in self.model.encode_batch(texts, add_special_tokens=False)]

    def _learn(self, words: list[str]) -> None:
        """Letters after a space split off again when they are joined, so they take one call."""
        plain = [w for w in words if w[0] == " " and w[1:].isalpha()]
        if plain:
            found = self.model.encode("".join(plain), add_special_tokens=False)
            data, at = np.array(found.ids, "<u4").tobytes(), np.array(found.word_ids)
            ends = np.searchsorted(at, np.arange(len(plain)), "right").tolist()
            start = 0
            for w, end in zip(plain, ends, strict=True):
                self.memo[w] = data[4 * start : 4 * end]
                start = end
        rest = [w for w in words if w not in self.memo]
        self.memo.update(zip(rest, self._whole(rest), strict=True))

    def encode(self, text: str) -> np.ndarray:
        if not _PLAIN.match(text) or any(a in text for a in self.added):
            return np.frombuffer(self._whole([text])[0], "<u4")
        words = _SPLIT.findall(text)
        parts = list(map(self.memo.get, words))
        if None in parts:
            places = [i for i, p in enumerate(parts) if p is None]
            missing = list({words[i] for i in places})
            if len(self.memo) + len(missing) > MEMO_WORDS:
                self.memo.clear()
            self._learn(missing)
            for i in places:
                parts[i] = self.memo[words[i]]
        return np.frombuffer(b"".join(parts), "<u4")


_TOKENIZERS: dict[str, ByteTokenizer] = {}


def tokenizer(path: str) -> ByteTokenizer:
    if path not in _TOKENIZERS:
        _TOKENIZERS[path] = ByteTokenizer(path)
    return _TOKENIZERS[path]


def _write(batches: Iterator[pa.RecordBatch], folder: str, path: str, end_id: int, bits: int, chunk_ids: int) -> Iterator[pa.RecordBatch]:
    part = TaskContext.get().partitionId()
    writer, model, end = None, tokenizer(path), np.array([end_id], "<u4")
    for batch in batches:
        ids = batch.column(0).to_pylist()
        for doc_id, text in zip(ids, batch.column(1), strict=True):
            writer = writer or ShardWriter(folder, f"shard-{part:08d}.ids", bits, chunk_ids)
            writer.add(doc_id, np.concatenate([model.encode(text.as_py() or ""), end]))
    if writer:
        writer.close()
        yield pa.RecordBatch.from_pydict({"part": pa.array([part], pa.int32()), "n_docs": pa.array([len(writer.docs)], pa.int64()), "n_ids": pa.array([writer.total], pa.int64())})


def write_token_files(docs: DataFrame, folder: str, tokenizer_path: str, end_id: int = 2, bits: int = 1, chunk_ids: int = CHUNK_IDS) -> list[tuple[str, int, int]]:
    """Encode (doc_id, text), append ``end_id`` to each document, write shards to ``folder`` in ascending doc_id order.

    Returns (uri, number of documents, number of ids) of each shard in order: as many entries as tasks. Null texts count
    as empty (the end id alone); null doc_ids come first; rows with the same doc_id are ordered by text. A shard is
    written under another name and renamed when whole, so that a task that is run again leaves the same file.
    """
    workers(docs.sparkSession)
    pa.fs.FileSystem.from_uri(folder)[0].create_dir(pa.fs.FileSystem.from_uri(folder)[1], recursive=True)
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    rows = rows.repartitionByRange(F.col("doc_id").asc()).sortWithinPartitions("doc_id", "text")
    done = rows.mapInArrow(partial(_write, folder=folder, path=tokenizer_path, end_id=end_id, bits=bits, chunk_ids=chunk_ids), "part int, n_docs long, n_ids long").collect()
    return [(f"{folder}/shard-{r.part:08d}.ids", r.n_docs, r.n_ids) for r in sorted(done)]


def _read(batches: Iterator[pd.DataFrame], with_ids: bool) -> Iterator[pd.DataFrame]:
    for pdf in batches:
        for uri, start in zip(pdf["uri"], pdf["start"], strict=True):
            rows, at = [], int(start)
            for doc_id, ids in ShardReader(uri).documents():
                row = (doc_id, at, len(ids), zlib.crc32(ids.astype("<u4").tobytes()))
                rows.append((*row, ids.astype(np.int64).tolist()) if with_ids else row)
                at += len(ids)
                if len(rows) == (256 if with_ids else 10_000):
                    yield _frame(rows, with_ids)
                    rows = []
            yield _frame(rows, with_ids)


def _frame(rows: list[tuple], with_ids: bool) -> pd.DataFrame:
    out = pd.DataFrame(rows, columns=["doc_id", "start", "n_tokens", "ids_crc32", *["ids"] * with_ids])
    return out.assign(doc_id=out["doc_id"].astype("Int64"))


def read_token_files(spark: SparkSession, shards: list[tuple[str, int, int]], with_ids: bool = False) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 (and ids) of every document in the shards, in a task for each shard."""
    workers(spark)
    schema = "doc_id long, start long, n_tokens long, ids_crc32 long" + ", ids array<long>" * with_ids
    starts, total = [], 0
    for uri, _, n in shards:
        starts.append((uri, total))
        total += n
    if not starts:
        return spark.createDataFrame([], schema)
    files = spark.createDataFrame(starts, "uri string, start long").repartition(len(starts))
    return files.mapInPandas(partial(_read, with_ids=with_ids), schema)


def write_and_read(docs: DataFrame, tokenizer_path: str, **options) -> DataFrame:
    """``write_token_files`` to a new folder of the shared ones, then ``read_token_files`` from it."""
    spark = docs.sparkSession
    return read_token_files(spark, write_token_files(docs, fresh_path(spark, "ids"), tokenizer_path, **options))
