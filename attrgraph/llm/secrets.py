"""Secret scans in DataFrame functions alone.

Three patterns give base spans. Beside them, long runs of key characters are judged by two character Markov
models, one of random strings and one of ordinary identifiers: the log-likelihood ratio of the run's transitions decides.
Both models are counted from labelled samples: strings made from hashes (random), and identifiers joined from the words
of whole texts of a bounded sample of the documents (ordinary).

Positions come from lengths: a text split by a pattern leaves the gaps between its matches, and running sums of gaps and
matches are code-point offsets. Running sums go block by block, so that a text's work stays in proportion to its matches, and an
expression that a lambda reads is put in a variable first, so that it isn't evaluated for each element.
"""

from __future__ import annotations

from collections.abc import Callable
from math import log

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# The base patterns of the contract. Runs of hex digits and access ids are maximal, so their least
# lengths can stand in the pattern; failing assignments still take up text, so those are filtered afterwards.
KINDS = ("assign", "access", "hex", "random")
ASSIGN = r"""(?i:(password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ACCESS = r"AKIA[A-Z0-9]{16,}"
HEX = r"[0-9a-f]{24,}"
RUN = r"[A-Za-z0-9+/_=-]{20,}"
LEAST_ASSIGNED = 6
SAMPLE_DOCS = 400
SAMPLE_STRINGS = 4000
RATIO_PER_CHARACTER = 0.7
REDACTED = "[SECRET]"
BLOCK = 128
_SPAN = "struct<start:int,kind:int,end:int>"


def labelled_samples(docs: DataFrame, n: int = SAMPLE_STRINGS, sample_docs: int = SAMPLE_DOCS) -> DataFrame:
    """(value, label): ``n`` random strings (1), and ordinary identifiers (0) of the whole texts of about ``sample_docs`` documents.

    Documents are drawn by a threshold on the hash of doc_id, so they are the same on every call and no task or driver gathers them.
    """
    spark = docs.sparkSession
    digest = F.concat(F.sha2(F.col("id").cast("string"), 256), F.sha2(F.concat(F.lit("x"), F.col("id").cast("string")), 256))
    coded = F.base64(F.unhex(digest))
    plain = F.regexp_replace(coded, "[+/=]", "")
    shape = F.col("id") % 5
    value = F.when(shape == 0, F.substring(coded, 1, 40)).when(shape == 1, F.substring(plain, 1, 36)).when(shape == 2, F.upper(F.substring(plain, 1, 24))).when(shape == 3, F.lower(F.substring(plain, 1, 32))).otherwise(F.concat_ws("-", F.substring(plain, 1, 12), F.substring(plain, 13, 12), F.substring(plain, 25, 12)))
    random = spark.range(n).select(value.alias("value"), F.lit(1).alias("label"))
    share = min(1.0, sample_docs / max(1, docs.select("doc_id").count()))
    keys = docs.select("doc_id", "text").where(F.pmod(F.xxhash64("doc_id"), F.lit(1 << 30)) < int(share * (1 << 30))).where("text is not null")
    words = F.filter(F.split("text", r"[^A-Za-z]+"), lambda w: F.length(w) > 1)
    triples = keys.select("doc_id", words.alias("w")).where(F.size("w") >= 3)
    triples = triples.select("doc_id", F.explode(F.sequence(F.lit(1), F.size("w") - 2, F.lit(3))).alias("i"), "w")
    a, b, c = (F.lower(F.element_at("w", F.col("i") + k)) for k in range(3))
    number = F.pmod(F.xxhash64("doc_id", "i"), F.lit(3000)).cast("string")
    form = F.pmod(F.xxhash64("i", "doc_id"), F.lit(6))
    joined = F.when(form == 0, F.concat_ws("_", a, b, c, number)).when(form == 1, F.concat_ws("-", a, b, number)).when(form == 2, F.concat(a, F.initcap(b), F.initcap(c), number)).when(form == 3, F.concat_ws("/", a, b, c, number)).when(form == 4, F.upper(F.concat_ws("_", a, b, number))).otherwise(F.concat(a, b, c, number))
    return random.union(triples.select(joined.alias("value"), F.lit(0).alias("label")))


def transition_ratios(samples: DataFrame) -> list[float]:
    """128 * 128 log-likelihood ratios of one ASCII character after another, with add-half smoothing.

    The counts are at most two tables of that fixed size.
    """
    chars = F.split("value", "")
    pairs = samples.where(F.length("value") > 1).select("label", F.explode(F.arrays_zip(F.slice(chars, 1, F.length("value") - 1).alias("a"), F.slice(chars, 2, F.length("value") - 1).alias("b"))).alias("p"))
    counted = pairs.select("label", F.ascii("p.a").alias("a"), F.ascii("p.b").alias("b")).where("a between 1 and 127 and b between 1 and 127").groupBy("label", "a", "b").agg(F.count("*").alias("n"))
    counts: list[dict[tuple[int, int], int]] = [{}, {}]
    totals: list[dict[int, int]] = [{}, {}]
    for r in counted.collect():
        counts[r.label][r.a, r.b] = r.n
        totals[r.label][r.a] = totals[r.label].get(r.a, 0) + r.n
    p = lambda k, a, b: log((counts[k].get((a, b), 0) + 0.5) / (totals[k].get(a, 0) + 33.0))
    return [p(1, a, b) - p(0, a, b) for a in range(128) for b in range(128)]


def ratio_of(value: Column, ratios: list[float]) -> Column:
    """Mean log-likelihood ratio per transition of an ASCII string of two characters at least."""
    table = F.split(F.lit(",".join(f"{x:.5f}" for x in ratios)), ",").cast("array<double>")
    chars = F.split(value, "")
    steps = F.zip_with(F.slice(chars, 1, F.length(value) - 1), F.slice(chars, 2, F.length(value) - 1), lambda a, b: F.element_at(table, F.ascii(a) * 128 + F.ascii(b) + 1))
    return F.aggregate(steps, F.lit(0.0), lambda s, x: s + x) / (F.length(value) - 1)


def _with(value: Column, use: Callable[[Column], Column]) -> Column:
    """``use`` of a value that is evaluated once."""
    return F.element_at(F.transform(F.array(value), use), 1)


def _scan(items: Column, zero: Column, kind: str, step: Callable[[Column, Column], Column], told: Callable[[Column, Column], Column]) -> Column:
    """What ``told`` (of the state before an element, and the element) gives for each element, in order; states start with ``zero``
    and follow by ``step``. An array of SQL type ``kind``."""
    empty = F.array().cast(f"array<{kind}>")

    def element(state: Column, x: Column) -> Column:
        return F.struct(step(state["at"], x).alias("at"), F.concat(state["out"], F.array(told(state["at"], x)).cast(f"array<{kind}>")).alias("out"))

    def all_of(xs: Column) -> Column:
        def block(state: Column, b: Column) -> Column:
            done = F.aggregate(F.slice(xs, b * BLOCK + 1, BLOCK), F.struct(state["at"].alias("at"), empty.alias("out")), element)
            return _with(done, lambda d: F.struct(d["at"].alias("at"), F.concat(state["out"], F.array(d["out"])).alias("out")))

        blocks = F.sequence(F.lit(0), F.floor((F.size(xs) - 1) / BLOCK).cast("int"))
        return F.aggregate(blocks, F.struct(zero.alias("at"), F.array().cast(f"array<array<{kind}>>").alias("out")), block, lambda s: F.flatten(s["out"]))

    return _with(items, lambda xs: F.when(F.size(xs) > 0, all_of(xs)).otherwise(empty))


def _placed(text: Column, pattern: str, matches: Column, kind: int, keep: Callable[[Column], Column] | None = None) -> Column:
    """Spans, in code points, of the matches that ``keep`` holds for."""
    steps = F.zip_with(F.slice(F.split(text, pattern, -1), 1, F.size(matches)), matches, lambda g, m: F.struct(F.length(g).alias("gap"), F.length(m).alias("size"), (keep(m) if keep else F.lit(True)).alias("keep")))
    begin = lambda at, x: (at + x["gap"]).cast("int")
    end = lambda at, x: (at + x["gap"] + x["size"]).cast("int")
    told = lambda at, x: F.when(x["keep"], F.struct(begin(at, x).alias("start"), F.lit(kind).alias("kind"), end(at, x).alias("end")))
    spans = F.filter(_scan(steps, F.lit(0), _SPAN, end, told), lambda x: x.isNotNull())
    return F.when(F.size(matches) > 0, spans).otherwise(F.array().cast(f"array<{_SPAN}>"))


def _apart(random: Column, base: Column) -> Column:
    """The spans of ``random`` that overlap none of ``base``."""
    is_random = lambda x: x["kind"] == len(KINDS) - 1
    span = lambda x: F.struct(*[x[c].alias(c) for c in ("start", "kind", "end")])
    # forwards: the furthest end of a base span before; backwards: the start of the next one
    furthest = lambda at, x: F.when(is_random(x), at).otherwise(F.greatest(at, x["end"]))
    following = lambda at, x: F.when(is_random(x), at).otherwise(x["start"])
    clear = _scan(F.sort_array(F.concat(random, base)), F.lit(0), _SPAN, furthest, lambda at, x: F.when(~is_random(x) | (x["start"] >= at), span(x)))
    clear = F.reverse(F.filter(clear, lambda x: x.isNotNull()))
    clear = _scan(clear, F.lit(2**31 - 1), _SPAN, following, lambda at, x: F.when(is_random(x) & (x["end"] <= at), span(x)))
    return F.when(F.size(random) > 0, F.reverse(F.filter(clear, lambda x: x.isNotNull()))).otherwise(random)


def with_spans(docs: DataFrame, ratios: list[float], threshold: float = RATIO_PER_CHARACTER) -> DataFrame:
    """``docs`` with ``base_spans`` and ``all_spans``, each sorted by start and kind. Null text: no spans."""
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    keep = (lambda m: F.length(F.regexp_extract(m, ASSIGN, 2)) >= LEAST_ASSIGNED, None, None, lambda m: ratio_of(m, ratios) >= threshold)
    found = docs.select(*docs.columns, *[F.regexp_extract_all(text, F.lit(p), F.lit(0)).alias(f"__{k}") for k, p in zip(KINDS, (ASSIGN, ACCESS, HEX, RUN), strict=True)])
    placed = found.select(*docs.columns, *[_placed(text, p, F.col(f"__{k}"), i, keep[i]).alias(f"__{k}") for i, (k, p) in enumerate(zip(KINDS, (ASSIGN, ACCESS, HEX, RUN), strict=True))])
    based = placed.select(*docs.columns, F.sort_array(F.concat("__assign", "__access", "__hex")).alias("base_spans"), "__random")
    random = _with(F.struct(F.col("__random").alias("r"), F.col("base_spans").alias("b")), lambda x: _apart(x["r"], x["b"]))
    return based.select(*docs.columns, "base_spans", F.sort_array(F.concat("base_spans", random)).alias("all_spans"))


def written(spans: str) -> Column:
    """kind:start:end of each span, joined by commas."""
    names = F.array(*[F.lit(k) for k in KINDS])
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", F.element_at(names, s["kind"] + 1), s["start"].cast("string"), s["end"].cast("string"))), ",")


def scan(docs: DataFrame, ratios: list[float] | None = None) -> DataFrame:
    """doc_id, n_assign, n_access, n_hex, base_sha256, spans of every row of (doc_id, text).

    Null and empty texts have no spans; rows stand alone, so repeated rows, null doc_ids and other columns make no
    difference; an empty table gives an empty result. Very long texts are scanned whole, in proportion to their length and
    matches. Where documents give no identifiers to learn from, the ordinary model is uniform.
    """
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    found = with_spans(rows, ratios or transition_ratios(labelled_samples(rows)))
    count = lambda k: F.size(F.filter("base_spans", lambda s: s["kind"] == k)).cast("long")
    return found.select("doc_id", *[count(k).alias(f"n_{KINDS[k]}") for k in range(3)], F.sha2(written("base_spans"), 256).alias("base_sha256"), written("all_spans").alias("spans"))


def redact(docs: DataFrame, ratios: list[float] | None = None) -> DataFrame:
    """``docs`` with its columns, where every stretch of overlapping spans in ``text`` is replaced by one mark.

    Null texts stay null, texts without spans as they are; repeated rows, null ids and clashing column names make no difference.
    """
    clash = {c: f"__{i}" for i, c in enumerate(docs.columns) if c != "text"}
    plain = docs.select(*[F.col(f"`{c}`").alias(clash.get(c, c)) for c in docs.columns])
    found = with_spans(plain, ratios or transition_ratios(labelled_samples(docs.select("doc_id", "text"))))
    text = F.col("text")
    # a stretch is told as the end of what was covered before it, and its own start and end
    told = _scan(F.col("all_spans"), F.lit(0), "struct<before:int,start:int,end:int,first:boolean>", lambda at, s: F.greatest(at, s["end"]), lambda at, s: F.when(s["end"] > at, F.struct(at.alias("before"), F.greatest(at, s["start"]).alias("start"), s["end"].alias("end"), (s["start"] >= at).alias("first"))))
    told = F.filter(told, lambda x: x.isNotNull())

    def rebuilt(x: Column) -> Column:
        spans, whole = x["spans"], x["text"]
        last = F.element_at(spans, -1)["end"]

        def block(b: Column) -> Column:  # a block's stretch of the text is cut out once, so that places in it are near
            some = F.slice(spans, b * BLOCK + 1, BLOCK)
            begin = F.element_at(some, 1)["before"]
            cut = F.struct(some.alias("some"), begin.alias("begin"), F.substring(whole, begin + 1, F.element_at(some, -1)["end"] - begin).alias("part"))
            mark = lambda c, s: F.concat(F.substring(c["part"], s["before"] - c["begin"] + 1, s["start"] - s["before"]), F.when(s["first"], REDACTED).otherwise(""))
            return _with(cut, lambda c: F.array_join(F.transform(c["some"], lambda s: mark(c, s)), ""))

        blocks = F.sequence(F.lit(0), F.floor((F.size(spans) - 1) / BLOCK).cast("int"))
        return F.concat(F.array_join(F.transform(blocks, block), ""), F.substring(whole, last + 1, F.length(whole) - last))

    clean = F.when(F.size("all_spans") > 0, _with(F.struct(told.alias("spans"), text.alias("text")), rebuilt)).otherwise(text)
    return found.select(*[clean.alias("text") if c == "text" else F.col(clash[c]).alias(c) for c in docs.columns])
