"""Exact SentencePiece merge-type (BPE) encoding by backtracking, and decoding.

A sequence of pieces is the encoding of a text just when every adjacent pair is what merging gives for
the two pieces' joint text. So: take the longest piece at a position (found for all positions by one
Aho-Corasick pass), accept it if it is compatible with the piece before it, else try the next shorter piece,
else mark the position as failed and step back. Compatibility is checked by re-merging the pair's text and
kept in a memo.

Merges never cross the start of a white-space run, nor a character outside the vocabulary, so a text falls
into units (white space and the word after it) whose encodings are kept in a bounded memo. Pieces made of
several spaces share one score, which breaks the strict order the backtracking needs: units that begin
with two or more spaces are merged directly.
"""

from __future__ import annotations

import hashlib
import heapq
import re
from collections.abc import Iterator
from functools import partial

import ahocorasick
import numpy as np
import pyarrow as pa
import sentencepiece
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from attrgraph.session import kept, lean, workers

SPACE = "▁"
MEMO_UNITS = 250_000
MEMO_PAIRS = 150_000
_UNITS = re.compile(r" +[^ \n]*|\n[^ \n]*")


class PieceCodec:
    """Encoder and decoder for one model file (BPE, identity normaliser, dummy prefix, byte fallback)."""

    def __init__(self, path: str):
        sp = sentencepiece.SentencePieceProcessor(model_file=path)
        ids = range(sp.get_piece_size())
        self.text = [sp.id_to_piece(i) for i in ids]
        self.special = {i for i in ids if sp.is_control(i) or sp.is_unknown(i)}
        self.byte_of = {i: int(self.text[i][3:5], 16) for i in ids if sp.is_byte(i)}
        self.id_of_byte = {b: i for i, b in self.byte_of.items()}
        self.unknown = sp.unk_id()
        self.unknown_text = " ⁇ "
        self.rank = {self.text[i]: (-sp.get_score(i), i) for i in ids if i not in self.special and i not in self.byte_of}
        if any(SPACE in p.lstrip(SPACE) or "\n" in p or " " in p for p in self.rank):
            raise ValueError("pieces with inner white space aren't supported")
        self.automaton = ahocorasick.Automaton()
        usable = [p for p in self.rank if p.count(SPACE) < 2 and self.merge(p) == [p]]
        for p in usable:
            self.automaton.add_word(p, p)
        self.automaton.make_automaton()
        kept = set(usable)
        self.shorter = {p: next((p[:k] for k in range(len(p) - 1, 0, -1) if p[:k] in kept), None) for p in usable}
        # each memo has a young and an old generation of at most that size
        self.pairs: dict[tuple[str, str], bool] = {}
        self.old_pairs: dict[tuple[str, str], bool] = {}
        self.units: dict[str, str] = {}
        self.old_units: dict[str, str] = {}
        self.odd: dict[str, str] = {}

    def merge(self, text: str) -> list[str]:
        """Pieces of ``text`` by merging the best-scored adjacent pair, leftmost first, until none is left."""
        parts, rank = list(text), self.rank
        n = len(parts)
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        heap = []

        def offer(i: int, j: int) -> None:
            if (r := rank.get(parts[i] + parts[j])) is not None:
                heapq.heappush(heap, (r[0], i, j, parts[i], parts[j]))

        for i in range(n - 1):
            offer(i, i + 1)
        while heap:
            _, i, j, one, two = heapq.heappop(heap)
            if parts[i] != one or parts[j] != two or after[i] != j:
                continue
            parts[i], parts[j] = one + two, ""
            after[i] = after[j]
            if after[i] < n:
                before[after[i]] = i
                offer(i, after[i])
            if before[i] >= 0:
                offer(before[i], i)
        return [p for p in parts if p]

    def compatible(self, one: str, two: str) -> bool:
        key = (one, two)
        known = self.pairs.get(key)
        if known is None:
            known = self.old_pairs.get(key)
            if known is None:
                known = self.merge(one + two) == [one, two]
            if len(self.pairs) >= MEMO_PAIRS:
                self.pairs, self.old_pairs = {}, self.pairs
            self.pairs[key] = known
        return known

    def split(self, text: str) -> list[str]:
        """Pieces (characters without a piece stand alone) of a unit, by backtracking."""
        longest = list(text)
        for end, piece in self.automaton.iter(text):
            start = end - len(piece) + 1
            if len(piece) >= len(longest[start]):
                longest[start] = piece
        n, at, failed, out = len(text), 0, 0, []
        piece = longest[0]
        while True:
            end = at + len(piece)
            if not failed >> end & 1 and (not out or self.compatible(out[-1], piece)):
                out.append(piece)
                if end == n:
                    return out
                at, piece = end, longest[end]
                continue
            piece = self.shorter.get(piece)
            while piece is None:
                failed |= 1 << at
                piece = out.pop()
                at -= len(piece)
                piece = self.shorter.get(piece)

    def unit_ids(self, unit: str) -> list[int]:
        text = unit.replace(" ", SPACE)
        out: list[int] = []
        for p in self.merge(text) if text.startswith(SPACE * 2) else self.split(text):
            if (r := self.rank.get(p)) is not None:
                out.append(r[1])
            elif self.id_of_byte:
                out += [self.id_of_byte[b] for b in p.encode()]
            else:
                out.append(self.unknown)
        return out

    def _unit(self, unit: str) -> str:
        """A unit's ids as text; what they decode to is checked here and kept apart where it isn't the unit itself."""
        value = self.units.get(unit) or self.old_units.get(unit)
        if value is None:
            ids = self.unit_ids(unit)
            value = ",".join(map(str, ids))
            if (back := self.surface(ids)) != unit:
                if len(self.odd) >= MEMO_UNITS:
                    self.odd, self.units, self.old_units = {}, {}, {}
                self.odd[unit] = back
        if len(self.units) >= MEMO_UNITS:
            self.units, self.old_units = {}, self.units
        self.units[unit] = value
        return value

    def encode_units(self, text: str) -> tuple[list[str], list[str]]:
        """The units of a text (with the dummy prefix), and the ids of each as text."""
        if not text:
            return [], []
        units = _UNITS.findall(" " + text.replace(SPACE, " "))
        known, unit = self.units.get, self._unit
        return units, [known(u) or unit(u) for u in units]

    def decode_units(self, units: list[str]) -> str:
        """What the ids of a text's units decode to: the dummy prefix is the first unit's first space."""
        odd = self.odd
        return "".join([odd.get(u, u) for u in units] if odd else units)[1:]

    def encode(self, text: str) -> list[int]:
        return [int(i) for ids in self.encode_units(text)[1] for i in ids.split(",")]

    def surface(self, ids: list[int]) -> str:
        """What ids stand for, with white space that the encoder put in front still there."""
        out, pending = [], bytearray()
        for i in ids:
            if i in self.byte_of:
                pending.append(self.byte_of[i])
                continue
            if pending:
                out.append(pending.decode("utf-8", "replace"))
                pending.clear()
            if i == self.unknown:
                out.append(self.unknown_text)
            elif i not in self.special:
                out.append(self.text[i].replace(SPACE, " "))
        if pending:
            out.append(pending.decode("utf-8", "replace"))
        return "".join(out)

    def decode(self, ids: list[int]) -> str:
        text = self.surface(ids)
        first = next((i for i in ids if i not in self.special), None)
        return text[1:] if first is not None and self.text[first].startswith(SPACE) else text


_CODECS: dict[str, PieceCodec] = kept("pieces")


def codec(path: str) -> PieceCodec:
    """The codec of a file, built once in each process."""
    if path not in _CODECS:
        _CODECS[path] = PieceCodec(path)
    return _CODECS[path]


def _round_trip(batches: Iterator[pa.RecordBatch], path: str, with_ids: bool) -> Iterator[pa.RecordBatch]:
    model = codec(path)
    for batch in batches:
        counts, digests, decoded, lists, texts = [], [], [], [], []
        for text in batch.column(1):
            units, parts = model.encode_units(text.as_py() or "")
            ids, back = ",".join(parts), model.decode_units(units)
            counts.append(ids.count(",") + 1 if ids else 0)
            digests.append(hashlib.sha256(ids.encode()).hexdigest())
            decoded.append(hashlib.sha256(back.encode()).hexdigest())
            if with_ids:
                lists.append(np.fromstring(ids, np.int32, sep=","))
                texts.append(back)
        columns = [batch.column(0), pa.array(counts, pa.int64()), pa.array(digests, pa.string()), pa.array(decoded, pa.string())]
        names = ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"]
        if with_ids:
            columns += [pa.array(lists, pa.list_(pa.int32())), pa.array(texts, pa.string())]
            names += ["ids", "decoded"]
        yield pa.RecordBatch.from_arrays(columns, names)


def encode_and_decode(docs: DataFrame, model_path: str, with_ids: bool = False) -> DataFrame:
    """Encode and decode every whole text of (doc_id, text) with the model at ``model_path``.

    Returns doc_id, n_tokens, SHA-256 of the ids and of the decoded text; with ``with_ids`` also ids and the decoded
    text. A null text counts as empty: no ids, empty decoding. Each row stands alone: repeated rows and null
    doc_ids pass through, other columns are ignored, an empty table gives an empty result. The model file must be
    readable on every worker (it belongs to an installed package). Very long texts are encoded whole, unit by unit.
    """
    workers(docs.sparkSession)
    schema = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string" + ", ids array<int>, decoded string" * with_ids
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return rows.mapInArrow(lean(partial(_round_trip, path=model_path, with_ids=with_ids), "pieces"), schema)
