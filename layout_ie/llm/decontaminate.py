"""Benchmark decontamination by one Aho-Corasick automaton over item windows.

Texts and items are lower-cased (A-Z) and cut into words; what lies between
words becomes one space.  Each window of ``size`` consecutive words of an item (an
item with fewer words is one window) is a pattern that starts and ends with a
space.  A worker builds the automaton once, scans each whole text once, and maps
the matches back to word numbers and to offsets in the original text.

The items travel to the workers only within ``MAX_CHARS`` characters; larger item
sets are cut into blocks by item hash and the blocks are scanned one after the
other, each with an automaton of bounded size.

Defined results: a null or wordless text has no words and no hits; null or
wordless items and items without an id are ignored; items that share an id count once;
repeated documents are scanned each; empty tables give empty results.
"""

from __future__ import annotations

import hashlib
import re
from collections import defaultdict
from collections.abc import Iterable, Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import shipped
from .common import settle

WINDOW = 10
#: Characters of item text in one automaton; windows multiply them by about six nodes each.
MAX_CHARS = 2_000_000
#: What is not a word, after lower-casing: fixed by the definition of a word.
_WORD = re.compile(rb"[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+")
_TABLE = bytes(
    c + 32 if 65 <= c <= 90 else c if 48 <= c <= 57 or 97 <= c <= 122 or c >= 128 else 32 for c in range(256)
)


def normal_words(text: bytes | None) -> list[bytes]:
    return (text or b"").translate(_TABLE).split()


def windows(words: list[bytes], size: int = WINDOW) -> set[bytes]:
    if not words:
        return set()
    return {b" ".join(words[i : i + size]) for i in range(max(1, len(words) - size + 1))}


@lru_cache(maxsize=2)
def automaton(items: tuple[tuple[str, bytes], ...], size: int):  # noqa: ANN201
    """Automaton whose values are (number of words, ids of the items with the window)."""
    import ahocorasick

    owners: dict[bytes, set[str]] = defaultdict(set)
    for item, text in items:
        for w in windows(normal_words(text), size):
            owners[w].add(item)
    machine = ahocorasick.Automaton()
    for w, ids in owners.items():
        machine.add_word(f" {w.decode('utf-8', 'replace')} ", (w.count(b" ") + 1, frozenset(ids)))
    if owners:
        machine.make_automaton()
    return machine


def scan(text: bytes | None, machine) -> tuple[int, list[tuple[int, int]], set[str]]:  # noqa: ANN001
    """Number of words, hit runs as half-open word ranges, ids of the items found."""
    words = normal_words(text)
    if not words or not len(machine):
        return len(words), [], set()
    flat = f" {b' '.join(words).decode('utf-8', 'replace')} "
    found, ends, items = [], [], set()
    for end, (k, ids) in machine.iter(flat):
        ends.append(end)
        found.append(k)
        items |= ids
    if not ends:
        return len(words), [], items
    gaps = np.flatnonzero(np.frombuffer(flat.encode("utf-32-le"), np.uint32) == 32)
    stops = np.searchsorted(gaps, ends)
    runs: list[tuple[int, int]] = []
    for a, b in sorted(zip((stops - found).tolist(), stops.tolist(), strict=True)):
        if runs and a <= runs[-1][1]:
            runs[-1] = (runs[-1][0], max(b, runs[-1][1]))
        else:
            runs.append((a, b))
    return len(words), runs, items


def original_spans(text: bytes, runs: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """Half-open code point ranges of the runs in the text as it was."""
    at = [m.span() for m in _WORD.finditer(text)]
    return [(len(text[: at[a][0]].decode("utf-8", "replace")), len(text[: at[b - 1][1]].decode("utf-8", "replace"))) for a, b in runs]


def _merge(old: Iterable[tuple[int, int]], new: Iterable[tuple[int, int]]) -> list[tuple[int, int]]:
    out: list[tuple[int, int]] = []
    for a, b in sorted([*old, *new]):
        if out and a <= out[-1][1]:
            out[-1] = (out[-1][0], max(b, out[-1][1]))
        else:
            out.append((a, b))
    return out


_RUNS = pa.list_(pa.struct([("first", pa.int64()), ("stop", pa.int64())]))
_SPANS = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))


def _scan_block(rows: DataFrame, keep: list[str], items: tuple[tuple[str, bytes], ...], size: int) -> DataFrame:
    """Adds what one automaton finds to the columns ``runs``, ``spans`` and ``items`` found so far."""
    schema = ", ".join(
        [*(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.select(*keep).schema), "n_words long", "runs array<struct<first:long,stop:long>>", "spans array<struct<start:long,end:long>>", "items array<string>"]
    )
    seen = "items" in rows.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        machine = automaton(items, size)
        for batch in batches:
            n_words, runs, spans, names = [], [], [], []
            for i in range(batch.num_rows):
                text = batch.column("_text")[i].as_py()
                n, new, ids = scan(text, machine)
                if seen:
                    new = _merge(((x["first"], x["stop"]) for x in batch.column("runs")[i].as_py()), new)
                    ids = ids | set(batch.column("items")[i].as_py())
                n_words.append(n)
                runs.append(new)
                spans.append(original_spans(text, new) if new else [])
                names.append(sorted(ids))
            yield pa.RecordBatch.from_arrays(
                [*(batch.column(c) for c in keep), pa.array(n_words, pa.int64()),
                 pa.array([[{"first": a, "stop": b} for a, b in x] for x in runs], _RUNS),
                 pa.array([[{"start": a, "end": b} for a, b in x] for x in spans], _SPANS), pa.array(names, pa.list_(pa.string()))],
                [*keep, "n_words", "runs", "spans", "items"],
            )

    return shipped(rows).mapInArrow(run, schema)


def find_contamination(docs: DataFrame, benchmark: DataFrame, keep: tuple[str, ...] = ("doc_id",), text: str = "text", size: int = WINDOW, max_chars: int = MAX_CHARS) -> DataFrame:
    """``keep`` with n_words, hit runs (words), hit spans (code points) and items of each whole text."""
    asked = benchmark.where(F.col("item_id").isNotNull() & F.col("text").isNotNull()).select(F.col("item_id").cast("string").alias("item"), F.col("text").cast("binary").alias("body"))
    chars = asked.agg(F.coalesce(F.sum(F.octet_length("body")), F.lit(0))).first()[0]
    blocks = max(1, -(-chars // max_chars))
    rows = docs.select(*keep, F.col(text).cast("binary").alias("_text"))
    for block in range(blocks):
        own = asked if blocks == 1 else asked.where(F.pmod(F.xxhash64("item", "body"), F.lit(blocks)) == block)
        items = tuple(sorted((r["item"], bytes(r["body"])) for r in own.collect()))
        last = block == blocks - 1
        rows = _scan_block(rows, [*keep, *([] if last else ["_text"])], items, size)
        rows = rows if last else settle(rows, "scanned").drop("n_words")
    return rows


def report(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """Counts per document, with a digest of the sorted item ids."""
    hits = F.aggregate("runs", F.lit(0).cast("long"), lambda total, r: total + r["stop"] - r["first"])
    return find_contamination(docs, benchmark).select(
        "doc_id", "n_words", hits.alias("n_hit"), F.size("items").cast("long").alias("n_items"),
        F.sha2(F.array_join(F.array_sort("items"), ","), 256).alias("items_sha256"), (F.size("runs") > 0).alias("contaminated"), "spans",
    )


def stage(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """The documents without a hit, in their own columns."""
    names = {c: f"_own_{i}" for i, c in enumerate(docs.columns)}
    inner = docs.select(*(F.col(f"`{c}`").alias(v) for c, v in names.items()))
    found = find_contamination(inner, benchmark, keep=tuple(names.values()), text=names["text"])
    return found.where(F.size("runs") == 0).select(*(F.col(v).alias(k) for k, v in names.items()))


def brute_force(docs: list[tuple[int, str | None]], items: list[tuple[int, str | None]], size: int = WINDOW) -> list[tuple]:
    """The report by plain comparison of word lists, for small inputs."""
    word = re.compile("[^\x00-\x2f\x3a-\x60\x7b-\x7f]+")
    low = str.maketrans({chr(c): chr(c + 32) for c in range(65, 91)})
    cut = lambda t: word.findall((t or "").translate(low))
    out = []
    for doc, text in docs:
        words, hit, names = cut(text), set(), set()
        for item, body in items:
            w = cut(body)
            for i in range(max(1, len(w) - size + 1) if w else 0):
                part = w[i : i + size]
                for j in range(len(words) - len(part) + 1):
                    if words[j : j + len(part)] == part:
                        hit |= set(range(j, j + len(part)))
                        names.add(str(item))
        out.append((doc, len(words), len(hit), len(names), hashlib.sha256(",".join(sorted(names)).encode()).hexdigest(), bool(hit)))
    return out
