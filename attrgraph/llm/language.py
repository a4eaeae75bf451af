"""Language identification by compression.

Each language has a raw-content zstandard dictionary of its own text. A text is cut into blocks that
together hold all of it, each block is compressed with each dictionary, and the language whose blocks are
smallest in sum wins. A dictionary is a bounded sample: stretches from all over the chosen texts. A margin under ``reject_margin`` (share of the winner's size) marks the answer as
not reliable.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from functools import partial

import numpy as np
import pandas as pd
import zstandard as zstd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from attrgraph.session import workers

BLOCK = 4096
DICTIONARY_BYTES = 48 * 1024
SAMPLE_DOCS = 96
REJECT_MARGIN = 0.01
UNKNOWN = "und"
STRETCHES = 4
_MAYBE_LETTER = re.compile(r"[^\W\d_]")


def has_letter(text: str) -> bool:
    """Whether a character of a letter category occurs; numbers such as one half or Roman ones aren't letters."""
    return any(m[0].isalpha() for m in _MAYBE_LETTER.finditer(text))


def spread(data: bytes, size: int) -> bytes:
    """At most ``size`` bytes: stretches that stand evenly from the first to the last byte."""
    if len(data) <= size:
        return data
    each = max(1, (size - STRETCHES + 1) // STRETCHES)
    return b" ".join(data[i * (len(data) - each) // (STRETCHES - 1) :][: each] for i in range(STRETCHES))[:size]


def learn_dictionaries(labelled: DataFrame, docs_per_language: int = SAMPLE_DOCS, dictionary_bytes: int = DICTIONARY_BYTES) -> dict[str, bytes]:
    """Raw dictionaries of at most ``dictionary_bytes`` bytes from at most ``docs_per_language`` texts of a language.

    Of a text longer than its share, ``STRETCHES`` stretches are taken that lie evenly over the whole text.

    The sample is the bounded one that the contract allows: the rows of (doc_id, text, lang) with the smallest
    hash of doc_id. Only ids are ranked; texts are read again for the chosen ids alone.
    """
    usable = labelled.where(F.col("lang").isNotNull() & (F.length("text") > 0) & F.col("doc_id").isNotNull())
    order = Window.partitionBy("lang").orderBy(F.xxhash64("doc_id"), "doc_id")
    chosen = usable.select("doc_id", "lang").withColumn("place", F.row_number().over(order)).where(F.col("place") <= docs_per_language)
    ids = sorted({r.doc_id for r in chosen.select("doc_id").collect()})
    each = dictionary_bytes // STRETCHES
    cut = F.array_join(F.transform(F.sequence(F.lit(0), F.lit(STRETCHES - 1)), lambda i: F.substring("text", (i * (F.length("text") - each) / (STRETCHES - 1)).cast("int") + 1, F.lit(each))), " ")
    text = F.when(F.length("text") <= dictionary_bytes, F.col("text")).otherwise(cut)
    rows = usable.where(F.col("doc_id").isin(ids)).select("doc_id", "lang", text.alias("text")).collect() if ids else []
    texts: dict[str, list] = {}
    for r in sorted(rows, key=lambda r: (r.lang, r.doc_id, r.text)):
        texts.setdefault(r.lang, []).append(r.text.lower().encode())
    share = lambda parts: max(64, dictionary_bytes // max(1, len(parts)))
    out = {}
    for lang, parts in texts.items():
        # every sampled text gives its share; what short ones leave goes to the long ones
        size, kept = share(parts), []
        for p in sorted(parts, key=len):
            kept.append(spread(p, size))
            left = len(parts) - len(kept)
            if left:
                size = (dictionary_bytes - sum(map(len, kept))) // left
        out[lang] = b"\n".join(kept)[-dictionary_bytes:]
    return out


class Classifier:
    """Sizes of a text under every dictionary."""

    def __init__(self, dictionaries: dict[str, bytes], level: int = 6):
        self.languages = sorted(dictionaries)
        self.compressors = []
        for lang in self.languages:
            params = zstd.ZstdCompressionParameters.from_level(
                level, source_size=BLOCK, dict_size=len(dictionaries[lang]), min_match=4,
                format=zstd.FORMAT_ZSTD1_MAGICLESS, write_content_size=False, write_dict_id=False, write_checksum=False,
            )
            d = zstd.ZstdCompressionDict(dictionaries[lang], dict_type=zstd.DICT_TYPE_RAWCONTENT)
            d.precompute_compress(compression_params=params)
            self.compressors.append(zstd.ZstdCompressor(dict_data=d, compression_params=params))

    def sizes(self, text: str) -> np.ndarray:
        data = text.lower().encode()
        out = np.zeros(len(self.compressors))
        for i in range(0, len(data), BLOCK):
            block = data[i : i + BLOCK]
            out += [len(c.compress(block)) for c in self.compressors]
        return out

    def predict(self, text: str | None, reject_margin: float = REJECT_MARGIN) -> tuple[str, float, bool]:
        """(language, score 0..1, reliable); ``und``, 0, False for null, text without a letter, or nothing learnt."""
        if text is None or not self.languages or not has_letter(text):
            return UNKNOWN, 0.0, False
        sizes = self.sizes(text)
        best = int(np.argmin(sizes))
        weight = np.exp(-np.minimum(60.0, (sizes - sizes[best]) * 8 / (4 + np.sqrt(sizes[best]))))
        others = np.delete(sizes, best)
        margin = (others.min() - sizes[best]) / sizes[best] if len(others) else 1.0
        return self.languages[best], float(1 / weight.sum()), bool(margin >= reject_margin)


def _predict(batches: Iterator[pd.DataFrame], dictionaries: dict[str, bytes]) -> Iterator[pd.DataFrame]:
    model = Classifier(dictionaries)
    for pdf in batches:
        rows = [model.predict(t if isinstance(t, str) else None) for t in pdf["text"]]
        yield pd.DataFrame({"doc_id": pdf["doc_id"], "held_out": pdf["held_out"], "lang_pred": [r[0] for r in rows], "score": [r[1] for r in rows], "reliable": [r[2] for r in rows]})


def identify_languages(docs: DataFrame, folds: int = 5) -> DataFrame:
    """Predict the language of every whole text of (doc_id, text, lang).

    Documents whose crc32(doc_id as text) mod ``folds`` is 0 are held out of learning; so are those with a null
    doc_id, which count as not held out. Very long texts are compressed whole. A null text, one without a letter (the empty one too), and every text
    where nothing could be learnt give ``und`` with score 0. Repeated rows give repeated answers. Equal sizes go
    to the language that sorts first. Other columns are ignored; an empty table gives an empty result.
    """
    workers(docs.sparkSession)
    fold = F.pmod(F.crc32(F.col("doc_id").cast("string").cast("binary")), F.lit(folds))
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), F.col("lang").cast("string").alias("lang"), fold.alias("fold"))
    dictionaries = learn_dictionaries(docs.where("fold != 0"))
    plain = docs.select("doc_id", "text", F.coalesce(F.col("fold") == 0, F.lit(False)).alias("held_out"))
    return plain.mapInPandas(partial(_predict, dictionaries=dictionaries), "doc_id long, held_out boolean, lang_pred string, score double, reliable boolean")
