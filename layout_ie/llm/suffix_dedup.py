"""Removal of byte strings that occur more than once, by suffix sorting.

A string of ``length`` bytes that occurs twice has the same anchor in both
places: the leftmost smallest hash among its ``gram``-byte grams.  So suffixes
need comparing only where their anchors agree:

1. each document yields its anchors: the gram's hash, and a hash of all bytes
   of the windows that the anchor stands for (its context);
2. grams that occur once are left out; contexts with equal hashes form a class;
3. the members of a class go with their bytes to tasks that compare each with the class's
   representative, byte by byte: equal ones are repeated as a whole;
4. of classes that share a gram one representative each goes with
   its bytes to the task of the gram, which sorts all window suffixes deep-shallow:
   multikey quicksort on eight-byte characters down to a shallow depth, then blind
   tries for the groups with longer common prefixes, built a level at a time: each
   group takes a reference suffix, its members branch by the place and byte
   where they leave it.  Suffixes that reach ``length`` together are repeated.

Hashes only bring together what is then compared.  A class is dealt to as many tasks as it
needs, each with a copy of the representative.  A gram with very many classes is not sorted at once: each
window of its representatives becomes a context of its own, and goes through steps 2 and 3.

Defined results: a null or empty text has no bytes; a document shorter than
``length`` loses nothing; repeated rows are copies of each other and lose their windows
both; a null id is an id of its own; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import shipped
from .common import drop_written, release_memory, settle

LENGTH, GRAM = 200, 64
#: Bytes in one vectorised piece of a scan, at most 2**24 (a place takes 24 bits).
PIECE = 1 << 20
#: Contexts of a gram above which its windows are compared one by one, and members of a class in one task.
HOT, MEMBERS = 1500, 512
#: Bytes sorted by multikey quicksort before blind tries take over.
SHALLOW = 32
#: Bytes of contexts that are sorted at once.
SORT_BYTES = 1 << 22


# ---------------------------------------------------------------- anchors
def gram_hashes(buf: np.ndarray, gram: int = GRAM) -> np.ndarray:
    """A 64-bit hash of the ``gram`` (a power of two) bytes from each place."""
    h = (buf.astype(np.uint64) + np.uint64(1)) * np.uint64(0x9E3779B97F4A7C15)
    h ^= h >> np.uint64(32)
    step, factor = 1, 0xBF58476D1CE4E5B9
    while step < gram:
        n = len(h) - step
        g = h[:n] * np.uint64(factor)
        g += h[step:]
        h = g
        factor = (factor * factor + 2) & 0xFFFFFFFFFFFFFFFF | 1
        step *= 2
    h ^= h >> np.uint64(29)
    h *= np.uint64(0x94D049BB133111EB)
    h ^= h >> np.uint64(32)
    return h


def sliding_min(x: np.ndarray, width: int) -> np.ndarray:
    span = 1
    while span * 2 <= width:
        x = np.minimum(x[:-span], x[span:])
        span *= 2
    return np.minimum(x[: len(x) - (width - span)], x[width - span :]) if span < width else x


def pieces(texts: list[bytes | None], length: int) -> Iterator[list[tuple[int, int, bytes]]]:
    """Groups of (row, offset, bytes) up to the piece size; longer texts overlap by ``length - 1``."""
    group, size = [], 0
    for row, text in enumerate(texts):
        for a in range(0, max(1, len(text or b"") - length + 1), PIECE - length + 1):
            part = (text or b"")[a : a + PIECE]
            if len(part) < length:
                continue
            if size + len(part) > PIECE and group:
                yield group
                group, size = [], 0
            group.append((row, a, part))
            size += len(part)
    if group:
        yield group


def anchors(group: list[tuple[int, int, bytes]], length: int = LENGTH, gram: int = GRAM) -> tuple[np.ndarray, ...]:
    """(row, first window, windows, offset of the gram in the first window, gram hash, context hash) of each anchor."""
    import xxhash

    raw = b"".join(p for _, _, p in group)
    sizes = np.array([len(p) for _, _, p in group])
    ends = np.cumsum(sizes)
    starts = ends - sizes
    hashes = gram_hashes(np.frombuffer(raw, np.uint8), gram)
    keyed = (hashes & np.uint64(0xFFFFFFFFFF000000)) | np.arange(len(hashes), dtype=np.uint64)
    place = (sliding_min(keyed, length - gram + 1) & np.uint64(0xFFFFFF)).astype(np.int64)
    window = np.arange(len(place))
    part = np.repeat(np.arange(len(group)), sizes)[: len(place)]
    whole = window + length <= ends[part]
    window, place, part = window[whole], place[whole], part[whole]
    first = np.flatnonzero(np.concatenate(([True], (place[1:] != place[:-1]) | (part[1:] != part[:-1]))))
    lo, n = window[first], np.diff(np.append(first, len(window)))
    offset, part = place[first] - lo, part[first]
    digest = xxhash.xxh64_intdigest
    context = [digest(raw[a : a + m + length - 1], o * 1024 + m) for a, m, o in zip(lo.tolist(), n.tolist(), offset.tolist(), strict=True)]
    rows, shift = np.array([r for r, _, _ in group]), np.array([a for _, a, _ in group])
    return rows[part], lo - starts[part] + shift[part], n, offset, hashes[place[first]].view(np.int64), np.array(context, np.uint64).view(np.int64)


def _anchor_rows(docs: DataFrame, length: int, gram: int) -> DataFrame:
    """``doc_id, tk, gram, context, at``; ``at`` packs first window, windows and offset."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for group in pieces(batch.column("text").to_pylist(), length):
                row, lo, n, offset, kh, ch = anchors(group, length, gram)
                take = pa.array(row)
                yield pa.RecordBatch.from_arrays([batch.column("doc_id").take(take), batch.column("tk").take(take), pa.array(kh), pa.array(ch), pa.array(lo << 20 | n << 10 | offset)], ["doc_id", "tk", "gram", "context", "at"])

    return shipped(docs).mapInArrow(run, "doc_id long, tk long, gram long, context long, at long")


# ---------------------------------------------------------------- deep-shallow sorting
def _characters(buf: np.ndarray) -> np.ndarray:
    """The eight bytes from each place as one big-endian character; zero bytes follow the end."""
    long = np.concatenate((buf, np.zeros(8, np.uint8))).astype(np.uint64)
    out = np.zeros(len(buf), np.uint64)
    for k in range(8):
        out = (out << np.uint64(8)) | long[k : k + len(buf)]
    return out


def _regroup(group: np.ndarray, *keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Order by (group, keys) and the new group number of each sorted place."""
    order = np.lexsort((*keys[::-1], group))
    change = group[order][1:] != group[order][:-1]
    for k in keys:
        s = k[order]
        change = change | (s[1:] != s[:-1])
    return order, np.concatenate(([0], np.cumsum(change)))


def deep_shallow(buf: np.ndarray, suffixes: np.ndarray, length: int = LENGTH, shallow: int = SHALLOW) -> np.ndarray:
    """Group number of each suffix, equal for suffixes that share their first ``length`` bytes; -1 if alone."""
    chars = _characters(buf)
    out = np.full(len(suffixes), -1, np.int64)
    live, group = np.arange(len(suffixes)), np.zeros(len(suffixes), np.int64)
    # Shallow: multikey quicksort, an eight-byte character a round, only where a group is left.
    for depth in range(0, min(shallow, length) // 8 * 8, 8):
        if not len(live):
            return out
        order, number = _regroup(group, chars[suffixes[live] + depth])
        many = np.bincount(number)[number] > 1
        live, group = live[order][many], number[many]
    depth = np.full(len(live), min(shallow, length) // 8 * 8)
    done = 0
    # Deep: a blind-trie level a round.
    while len(live):
        order = np.argsort(group, kind="stable")
        live, group, depth = live[order], group[order], depth[order]
        head = np.concatenate(([True], group[1:] != group[:-1]))
        reference = suffixes[live[np.flatnonzero(head)]][np.cumsum(head) - 1]
        at = suffixes[live]
        left = depth.copy()  # where a member leaves its reference
        open_ = np.flatnonzero(left < length)
        while len(open_):
            diff = chars[at[open_] + left[open_]] ^ chars[reference[open_] + left[open_]]
            same = diff == 0
            differ = open_[~same]
            # Leading equal bytes of the character that differs.
            d = diff[~same]
            lead = np.zeros(len(d), np.int64)
            for k in range(7, 0, -1):
                lead += (d >> np.uint64(8 * k)) == 0
            left[differ] += lead
            open_ = open_[same]
            left[open_] += 8
            open_ = open_[left[open_] < length]
        left = np.minimum(left, length)
        through = left >= length
        if through.any():
            number = np.cumsum(head) - 1
            full = np.bincount(number[through], minlength=number[-1] + 1)
            twin = through & (full[number] > 1)
            out[live[twin]] = done + number[twin]
            done += int(number[-1]) + 1
        rest = np.flatnonzero(~through)
        if not len(rest):
            break
        byte = buf[at[rest] + left[rest]]
        order, number = _regroup(group[rest], left[rest], byte)
        many = np.bincount(number)[number] > 1
        kept = rest[order][many]
        live, group, depth = live[kept], number[many], left[kept] + 1
    return out


_NEED = "kind", "gram", "context", "at", "salts", "single"
#: What the bytes of a context are for: to be sorted, to compare members with, to be compared.
SORTED, REPRESENTATIVE, MEMBER = 0, 1, 2
_CONTEXT_DDL = "spread long, kind int, gram long, context long, doc_id long, tk long, first long, single boolean, body binary"


def _unpack(at: int) -> tuple[int, int, int]:
    return at >> 20, at >> 10 & 1023, at & 1023


def _window_rows(docs: DataFrame, length: int) -> DataFrame:
    """Each window of the contexts in ``need`` as a context of its own: rows like those of anchors."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import xxhash

        for batch in batches:
            out: list[tuple] = []
            for doc, tk, text, need in zip(*(batch.column(c).to_pylist() for c in ("doc_id", "tk", "text", "need")), strict=True):
                for x in need:
                    lo, n, offset = _unpack(x["at"])
                    for i in range(n):
                        context = xxhash.xxh64_intdigest(text[lo + i : lo + i + length], offset - i) - (1 << 63)
                        out.append((doc, tk, x["gram"], context, lo + i << 20 | 1 << 10 | offset - i))
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*out, strict=True)], ["doc_id", "tk", "gram", "context", "at"])

    return shipped(docs).mapInArrow(run, "doc_id long, tk long, gram long, context long, at long")


def _contexts(docs: DataFrame, length: int) -> DataFrame:
    """Bytes of the contexts that ``need`` lists per document, with the number (``spread``) by which they are dealt."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import struct

        import xxhash

        deal = lambda kind, *numbers: xxhash.xxh64_intdigest(struct.pack(f"<{len(numbers)}q", *numbers), kind) - (1 << 63)
        for batch in batches:
            rows = []
            for doc, tk, text, need in zip(*(batch.column(c).to_pylist() for c in ("doc_id", "tk", "text", "need")), strict=True):
                for x in need:
                    kind, gram, context, salts = x["kind"], x["gram"], x["context"], x["salts"]
                    lo, n, _ = _unpack(x["at"])
                    body = text[lo : lo + n + length - 1]
                    if kind == SORTED:
                        rows.append((deal(0, gram), kind, gram, context, doc, tk, lo, x["single"], body))
                    elif kind == MEMBER:
                        rows.append((deal(1, gram, context, deal(2, tk, lo) % salts), kind, gram, context, doc, tk, lo, False, body))
                    else:
                        rows += [(deal(1, gram, context, i), kind, gram, context, doc, tk, lo, False, body) for i in range(salts)]
            if rows:
                types = (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.bool_(), pa.binary())
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), types, strict=True)], ["spread", "kind", "gram", "context", "doc_id", "tk", "first", "single", "body"])

    return shipped(docs).mapInArrow(run, _CONTEXT_DDL)


_RUNS = ("doc_id", "tk", "first", "n")


def _run_rows(rows: list[tuple]) -> pa.RecordBatch:
    columns = zip(*rows, strict=True) if rows else [[] for _ in _RUNS]
    return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in columns], list(_RUNS))


def _decided_runs(contexts: DataFrame, length: int) -> DataFrame:
    """Runs of repeated windows: ``doc_id, tk, first, n``.  Rows come sorted by spread, gram, context and kind."""

    def judge(held: list[tuple]) -> list[tuple]:
        """Sort the window suffixes of whole grams; runs of the contexts that occur once."""
        sizes = np.array([len(r[4]) for r in held])
        buf = np.frombuffer(b"".join(r[4] for r in held), np.uint8)
        base = np.cumsum(sizes) - sizes
        n = sizes - length + 1
        owner = np.repeat(np.arange(len(held)), n)
        inner = np.arange(len(owner)) - np.repeat(np.cumsum(n) - n, n)
        twin = deep_shallow(buf, base[owner] + inner, length) >= 0
        hit = np.flatnonzero(twin & np.array([r[3] for r in held])[owner])
        if not len(hit):
            return []
        cut = np.flatnonzero(np.concatenate(([True], (np.diff(hit) != 1) | (owner[hit][1:] != owner[hit][:-1]))))
        who, first, runs = owner[hit][cut].tolist(), inner[hit][cut].tolist(), np.diff(np.append(cut, len(hit))).tolist()
        return [(held[w][0], held[w][1], held[w][2] + f, r) for w, f, r in zip(who, first, runs, strict=True)]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []
        size, last = 0, None
        known, body_of_class = None, b""
        for batch in batches:
            out: list[tuple] = []
            columns = (batch.column(c).to_pylist() for c in ("spread", "kind", "gram", "context", "doc_id", "tk", "first", "single", "body"))
            for spread, kind, gram, context, doc, tk, first, single, body in zip(*columns, strict=True):
                if kind == SORTED:
                    if spread != last and size >= SORT_BYTES:
                        out += judge(held)
                        held, size = [], 0
                    held.append((doc, tk, first, single, body))
                    size += len(body)
                    last = spread
                elif kind == REPRESENTATIVE:
                    known, body_of_class = (spread, gram, context), body
                elif (spread, gram, context) != known or body != body_of_class:
                    raise ValueError("different contexts have one 128-bit hash")
                else:
                    out.append((doc, tk, first, len(body) - length + 1))
            if out:
                yield _run_rows(out)
        if held:
            yield _run_rows(judge(held))
        del held
        release_memory()

    return shipped(contexts).mapInArrow(run, "doc_id long, tk long, first long, n long")


# ---------------------------------------------------------------- operator
def _keyed(docs: DataFrame, text: str) -> DataFrame:
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64(F.col(text)).alias("tk"), F.col(text).cast("binary").alias("text"))


def repeated_windows(docs: DataFrame, text: str = "text", length: int = LENGTH, gram: int = GRAM) -> DataFrame:
    """``doc_id, tk, first, n``: runs of window starts whose ``length`` bytes start elsewhere, too."""
    spark = docs.sparkSession
    rows = _keyed(docs, text)
    found = settle(_anchor_rows(rows.where(F.octet_length("text") >= length), length, gram), "anchors")
    # Written, so that the join reads both sides from exchanges and Spark may split a gram that very many places share.
    often = settle(found.groupBy("gram").agg(F.count("*").alias("_n")).where("_n > 1").select("gram"), "often")
    shared = settle(found.join(often, "gram", "left_semi"), "shared")
    drop_written(found)
    classes = _classes(shared, "contexts")
    per_gram = settle(classes.groupBy("gram").agg(F.count("*").alias("contexts")).where("contexts > 1"), "grams")
    need = [_members(shared, classes), _asked(classes.join(per_gram.where(F.col("contexts") <= HOT), "gram"), SORTED)]
    done = [often, shared, classes, per_gram]
    hot = per_gram.where(F.col("contexts") > HOT)
    if not hot.isEmpty():
        asked = _asked(classes.join(hot, "gram"), SORTED)
        windows = settle(_window_rows(_with_need(rows, asked), length), "windows")
        again = _classes(windows, "windowed")
        need.append(_members(windows, again))
        done += [windows, again]
    joined = _with_need(rows, reduce(DataFrame.unionByName, need))
    for table in done:
        drop_written(table)
    parts = max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))
    order = ("spread", "gram", "context", "kind")
    contexts = _contexts(joined, length).repartition(parts, "spread").sortWithinPartitions(*order)
    return settle(_decided_runs(contexts, length).distinct(), "runs")


def _classes(contexts: DataFrame, label: str) -> DataFrame:
    """``gram, context, copies, rep`` of contexts with equal hashes."""
    return settle(contexts.groupBy("gram", "context").agg(F.count("*").alias("copies"), F.min(F.struct("doc_id", "tk", "at")).alias("rep")), label)


def _salts(copies: str = "copies"):  # noqa: ANN202
    return F.ceil(F.col(copies) / MEMBERS).cast("int")


def _asked(classes: DataFrame, kind: int) -> DataFrame:
    """What is needed of the representatives' documents."""
    return classes.select(
        "rep.doc_id", "rep.tk", F.lit(kind).alias("kind"), "gram", "context", "rep.at", _salts().alias("salts"), (F.col("copies") == 1).alias("single")
    )


def _members(contexts: DataFrame, classes: DataFrame) -> DataFrame:
    """What is needed of all documents in classes of two or more, and of the representatives."""
    many = classes.where("copies > 1")
    own = contexts.join(many.select("gram", "context", "copies"), ["gram", "context"])
    own = own.select("doc_id", "tk", F.lit(MEMBER).alias("kind"), "gram", "context", "at", _salts().alias("salts"), F.lit(False).alias("single"))
    return own.unionByName(_asked(many, REPRESENTATIVE))


def _with_need(rows: DataFrame, asked: DataFrame) -> DataFrame:
    """The documents that are asked for, each with what is needed of it; repeated rows need the same once."""
    need = settle(asked.distinct().groupBy("doc_id", "tk").agg(F.collect_list(F.struct(*_NEED)).alias("need")), "need")
    need = need.select(F.col("doc_id").alias("_d"), F.col("tk").alias("_t"), "need")
    return rows.join(need, F.col("doc_id").eqNullSafe(F.col("_d")) & (F.col("tk") == F.col("_t"))).select("doc_id", "tk", "text", "need")


def remove_repeats(docs: DataFrame, text: str = "text", length: int = LENGTH, gram: int = GRAM) -> DataFrame:
    """``doc_id, n_bytes, n_removed, n_spans, kept_sha256, spans, kept`` of every row.

    ``spans`` are the removed byte ranges, ``kept`` the bytes that remain.
    """
    runs = repeated_windows(docs, text, length, gram)
    lists = settle(runs.groupBy("doc_id", "tk").agg(F.collect_list(F.struct("first", "n")).alias("runs")), "spans")
    lists = lists.select(F.col("doc_id").alias("_d"), F.col("tk").alias("_t"), "runs")
    joined = _keyed(docs, text).join(lists, F.col("doc_id").eqNullSafe(F.col("_d")) & (F.col("tk") == F.col("_t")), "left").select("doc_id", "text", "runs")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out: list[list] = [[], [], [], [], [], []]
            for text_, own in zip(batch.column("text").to_pylist(), batch.column("runs").to_pylist(), strict=True):
                body, spans = text_ or b"", []
                for a, n in sorted((r["first"], r["n"]) for r in own or []):
                    b = a + n + length - 1
                    if spans and a <= spans[-1][1]:
                        spans[-1] = (spans[-1][0], max(b, spans[-1][1]))
                    else:
                        spans.append((a, b))
                stops = [0, *(x for s in spans for x in s), len(body)]
                kept = b"".join(body[stops[i] : stops[i + 1]] for i in range(0, len(stops), 2))
                for col, x in zip(out, (len(body), len(body) - len(kept), len(spans), hashlib.sha256(kept).hexdigest(), [{"start": a, "end": b} for a, b in spans], kept), strict=True):
                    col.append(x)
            types = (pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())])), pa.binary())
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), *(pa.array(c, t) for c, t in zip(out, types, strict=True))], ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "spans", "kept"])

    return shipped(joined).mapInArrow(run, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, spans array<struct<start:long,end:long>>, kept binary")


def brute_force(docs: list[tuple[int, str | None]], length: int = LENGTH) -> list[tuple]:
    """The counts and digest by a table of all windows, for small inputs."""
    from collections import Counter

    bodies = [(d, (t or "").encode()) for d, t in docs]
    seen = Counter(b[i : i + length] for _, b in bodies for i in range(len(b) - length + 1))
    out = []
    for d, b in bodies:
        gone = bytearray(len(b))
        for i in range(len(b) - length + 1):
            if seen[b[i : i + length]] > 1:
                gone[i : i + length] = b"\1" * length
        flat = bytes(gone)
        spans = flat.count(b"\0\1") + flat.startswith(b"\1")
        kept = bytes(x for x, g in zip(b, gone, strict=True) if not g)
        out.append((d, len(b), sum(gone), spans, hashlib.sha256(kept).hexdigest()))
    return out
