"""The text algebra: relational operators, span extraction and span aggregation.

A relation is a DataFrame with a document key, ``begin`` and ``end`` (and any other
columns).  Extraction computes offsets inside one row, on the JVM; aggregation is one
sort per document (windows), never a comparison of all pairs.
"""

from __future__ import annotations

import re
from collections.abc import Callable, Iterator
from re import _parser as sre

import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..session import ship

MATCHES = "array<struct<begin:bigint,end:bigint,matched:string>>"


# ---------------------------------------------------------------- relational
def select(rel: DataFrame, predicate: Column) -> DataFrame:
    return rel.where(predicate)


def project(rel: DataFrame, *columns: str) -> DataFrame:
    return rel.select(*columns)


def join(a: DataFrame, b: DataFrame, predicate: Column | None = None, page: str = "page_id", across_pages: bool = False) -> DataFrame:
    """Join of ``a`` (alias a) and ``b`` (alias b) within a page; over all pages only if asked for."""
    left, right = a.alias("a"), b.alias("b")
    on = None if across_pages else F.col(f"a.{page}") == F.col(f"b.{page}")
    if predicate is not None:
        on = predicate if on is None else on & predicate
    return left.crossJoin(right) if on is None else left.join(right, on)


def product(a: DataFrame, b: DataFrame, page: str = "page_id", across_pages: bool = False) -> DataFrame:
    return join(a, b, None, page, across_pages)


def _same_width(a: DataFrame, b: DataFrame) -> None:
    if len(a.columns) != len(b.columns):
        raise ValueError(f"widths differ: {len(a.columns)} and {len(b.columns)}")


def union(a: DataFrame, b: DataFrame) -> DataFrame:
    _same_width(a, b)
    return a.union(b)


def intersect(a: DataFrame, b: DataFrame, all: bool = True) -> DataFrame:  # noqa: A002
    _same_width(a, b)
    return a.intersectAll(b) if all else a.intersect(b)


def difference(a: DataFrame, b: DataFrame, all: bool = True) -> DataFrame:  # noqa: A002
    _same_width(a, b)
    return a.exceptAll(b) if all else a.subtract(b)


# ---------------------------------------------------------------- extraction
#: Matches whose offsets are summed up in one array.
SLICE = 64


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """``body(value)`` with ``value`` computed once a row."""
    return F.element_at(F.transform(F.array(value), body), 1)


def match_offsets(text: Column, pattern: str) -> Column:
    """All matches with their offsets: running lengths of the gaps and the matches in turn."""
    found = F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    return let(F.arrays_zip(F.split(text, pattern, -1).alias("gap"), found.alias("hit")), _running)


def _running(pairs: Column) -> Column:
    """Matches with offsets from an array of (gap, match)."""

    def step(acc: Column, p: Column) -> Column:
        begin = acc["at"] + F.length(p["gap"])
        end = begin + F.coalesce(F.length(p["hit"]), F.lit(0))
        one = F.struct(begin.cast("long").alias("begin"), end.cast("long").alias("end"), p["hit"].alias("matched"))
        return F.struct(end.cast("long").alias("at"), F.when(p["hit"].isNotNull(), F.array_append(acc["out"], one)).otherwise(acc["out"]).alias("out"))

    def part(acc: Column, slice_: Column) -> Column:
        at = F.coalesce(F.try_element_at(acc, F.lit(-1))["at"], F.lit(0).cast("long"))
        return F.array_append(acc, F.aggregate(slice_, F.struct(at.alias("at"), F.array().cast(MATCHES).alias("out")), step))

    # Appending copies an array, so it is done in slices: the cost stays near linear for very long texts.
    slices = F.transform(F.sequence(F.lit(0), F.floor((F.size(pairs) - 1) / SLICE).cast("int")), lambda i: F.slice(pairs, i * SLICE + 1, F.lit(SLICE)))
    parts = F.aggregate(slices, F.array().cast(f"array<struct<at:bigint,out:{MATCHES}>>"), part)
    return F.flatten(F.transform(parts, lambda p: p["out"]))


#: What Java and not Python writes: a property class, which takes one character.
_JAVA_CLASS = re.compile(r"\\[pP](?:\{[^}]*\}|\w)")
_ZERO_WIDTH = re.compile(r"\\[bBAGZz]|[\^$]|\(\?<?[=!]")


def may_match_nothing(pattern: str) -> bool:
    """True if some match of the pattern may be empty: anchors and look-arounds take no width.

    A pattern whose width cannot be told is taken to have empty matches if it has parts without width.
    """
    try:
        return sre.parse(_JAVA_CLASS.sub("x", pattern)).getwidth()[0] == 0
    except re.error:
        return _ZERO_WIDTH.search(pattern) is not None


def regex_spans(docs: DataFrame, pattern: str, text: str = "text", keep: tuple[str, ...] = ("doc_id",), flags: str = "", group: int = 0) -> DataFrame:
    """Span and text of every match; ``flags`` are letters as in ``(?i)``, ``group`` the part that is the span.

    Patterns that may match nothing and spans of groups take the Arrow way, all others stay on the JVM.
    """
    pattern = f"(?{flags}){pattern}" if flags else pattern
    if group or may_match_nothing(pattern):
        return regex_spans_arrow(docs, pattern, text, keep, group)
    return docs.select(*keep, F.inline(match_offsets(F.col(text), pattern)))


def _arrow_rows(docs: DataFrame, text: str, keep: tuple[str, ...], find: Callable[[str], Iterator[tuple[int, int, str]]], last: str) -> DataFrame:
    """``keep``, begin, end and ``last`` for all that ``find`` yields of each text."""
    ship(docs.sparkSession)
    rows = docs.select(*keep, F.col(text).alias("_text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            at, begin, end, said = [], [], [], []
            for i, t in enumerate(batch.column(len(keep)).to_pylist()):
                for b, e, m in find(t or ""):
                    at.append(i)
                    begin.append(b)
                    end.append(e)
                    said.append(m)
            taken = [c.take(pa.array(at, pa.int64())) for c in batch.columns[: len(keep)]]
            yield pa.RecordBatch.from_arrays([*taken, pa.array(begin, pa.int64()), pa.array(end, pa.int64()), pa.array(said, pa.string())], [*keep, "begin", "end", last])

    schema = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.select(*keep).schema), f"begin long, end long, {last} string"])
    return rows.mapInArrow(run, schema)


def regex_spans_arrow(docs: DataFrame, pattern: str, text: str = "text", keep: tuple[str, ...] = ("doc_id",), group: int = 0) -> DataFrame:
    """The same by an engine in Python, for groups and empty matches; a group that takes no part has no span."""

    def find(t: str) -> Iterator[tuple[int, int, str]]:
        try:
            import regex as engine
        except ImportError:
            engine = re
        for m in engine.compile(pattern, engine.ASCII).finditer(t):
            if m.start(group) >= 0:
                yield m.start(group), m.end(group), m.group(group)

    return _arrow_rows(docs, text, keep, find, "matched")


TOKEN = r"[A-Za-z0-9_]+"
#: Dictionaries up to this many entries travel to the texts; larger ones meet them in a shuffle.
BROADCAST_TERMS = 200_000


def ascii_lower(text: Column) -> Column:
    """A-Z in lower case; other letters, some of which Unicode folds into these, stay."""
    return F.translate(text, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def token_key(text: Column) -> Column:
    """The words of a text in lower case, one blank between."""
    return F.array_join(F.regexp_extract_all(ascii_lower(text), F.lit(TOKEN), F.lit(0)), " ")


def dictionary(terms: DataFrame, max_words: int | None = None) -> tuple[DataFrame, list[int], int]:
    """The entries as ``_key, term``, how many words they have, and how many there are.  Wordless entries match nothing."""
    wanted = terms.select(token_key(F.col("term")).alias("_key"), "term").where("_key <> ''").distinct()
    sizes = {r["n"]: r["count"] for r in wanted.groupBy(F.size(F.split("_key", " ")).alias("n")).count().collect()}
    return wanted, sorted(n for n in sizes if max_words is None or n <= max_words), sum(sizes.values())


def dict_spans(docs: DataFrame, terms: DataFrame, text: str = "text", keep: tuple[str, ...] = ("doc_id",), max_words: int | None = None) -> DataFrame:
    """Every occurrence of every entry (any case, whole words): ``keep``, begin, end, term.

    ``terms`` has a column ``term``; its words and those of the text are compared as
    runs of as many tokens as some entry has.  Only a caller that sets ``max_words`` leaves longer entries out.
    Offsets are found in one pass over each text; a small dictionary goes along, so that only its
    occurrences leave the pass.
    """
    wanted, lengths, n_terms = dictionary(terms, max_words)
    known = {r["_key"] for r in wanted.select("_key").distinct().collect()} if n_terms <= BROADCAST_TERMS else None

    def find(t: str) -> Iterator[tuple[int, int, str]]:
        found = [(m.start(), m.end(), m.group().lower()) for m in re.finditer(TOKEN, t)]
        for n in lengths:
            for i in range(len(found) - n + 1):
                key = found[i][2] if n == 1 else " ".join(w for _, _, w in found[i : i + n])
                if known is None or key in known:
                    yield found[i][0], found[i + n - 1][1], key

    return _arrow_rows(docs, text, keep, find, "_key").join(F.broadcast(wanted) if known is not None else wanted, "_key").drop("_key")


def dict_rows(docs: DataFrame, terms: DataFrame, text: str = "text", keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """``keep`` and ``term``, once for each entry that a text holds: an equi-join of its distinct runs of words, without offsets."""
    wanted, lengths, n_terms = dictionary(terms)
    words = F.regexp_extract_all(ascii_lower(F.col(text)), F.lit(TOKEN), F.lit(0))
    runs = lambda w, n: w if n == 1 else F.transform(F.sequence(F.lit(1), F.greatest(F.size(w) - (n - 1), F.lit(0))), lambda i: F.array_join(F.slice(w, i, F.lit(n)), " "))
    # Of a text shorter than the run the sequence counts down from 1 to 0; its pieces are no entries.
    every = lambda w: F.flatten(F.array(*(F.when(F.size(w) >= n, runs(w, n)).otherwise(F.array().cast("array<string>")) for n in lengths or [1])))
    held = docs.where(F.col(text).isNotNull()).select(*keep, F.explode(F.array_distinct(let(words, every))).alias("_key"))
    return held.join(F.broadcast(wanted) if n_terms <= BROADCAST_TERMS else wanted, "_key").drop("_key")


# ---------------------------------------------------------------- aggregation
def consolidate_contained(rel: DataFrame, page: str = "doc_id") -> DataFrame:
    """Drop spans inside another span; equal spans count once."""
    w = Window.partitionBy(page).orderBy("begin", F.desc("end")).rowsBetween(Window.unboundedPreceding, -1)
    return rel.select(page, "begin", "end").distinct().withColumn("_far", F.max("end").over(w)).where(F.col("_far").isNull() | (F.col("end") > F.col("_far"))).drop("_far")


def islands(rel: DataFrame, page: str, broken: Column) -> DataFrame:
    """Number the runs of each page; ``broken`` says, from begin and ``_far`` (largest end before), where one starts."""
    w = Window.partitionBy(page).orderBy("begin", "end")
    far = rel.withColumn("_far", F.max("end").over(w.rowsBetween(Window.unboundedPreceding, -1)))
    return far.withColumn("island", F.sum(F.when(F.col("_far").isNull() | broken, 1).otherwise(0)).over(w.rowsBetween(Window.unboundedPreceding, 0))).drop("_far")


def consolidate_overlapping(rel: DataFrame, page: str = "doc_id") -> DataFrame:
    """Merge spans that overlap, transitively."""
    runs = islands(rel.select(page, "begin", "end"), page, F.col("begin") >= F.col("_far"))
    return runs.groupBy(page, "island").agg(F.min("begin").alias("begin"), F.max("end").alias("end")).drop("island")


def text_block(rel: DataFrame, min_count: int, max_gap: int, page: str = "doc_id") -> DataFrame:
    """Maximal runs of at least ``min_count`` spans with at most ``max_gap`` characters between neighbours."""
    runs = islands(rel.select(page, "begin", "end"), page, F.col("begin") - F.col("_far") > max_gap)
    blocks = runs.groupBy(page, "island").agg(F.min("begin").alias("begin"), F.max("end").alias("end"), F.count("*").alias("n_spans"))
    return blocks.where(F.col("n_spans") >= min_count).drop("island")


def follows_join(a: DataFrame, b: DataFrame, d: int, page: str = "doc_id") -> DataFrame:
    """Pairs where a span of ``a`` is followed by one of ``b`` within ``d`` characters.

    A range join by buckets of ``d + 1`` characters: the follower begins in the bucket where the first one
    ends or in the next.
    """
    width = d + 1
    left = a.select(page, F.col("begin").alias("a_begin"), F.col("end").alias("a_end"))
    left = left.withColumn("_bucket", F.explode(F.array(F.floor(F.col("a_end") / width), F.floor(F.col("a_end") / width) + 1)))
    right = b.select(page, F.col("begin").alias("b_begin"), F.col("end").alias("b_end")).withColumn("_bucket", F.floor(F.col("b_begin") / width))
    return left.join(right, [page, "_bucket"]).where((F.col("a_end") <= F.col("b_begin")) & (F.col("b_begin") - F.col("a_end") <= d)).drop("_bucket")
