"""Content-addressed store of token ids.

Documents are encoded by words: the tokenizer drops white space before it merges,
so a text's ids are those of its white-space-separated words in order, and a
slice of texts encodes each of its distinct words once.  (A tokenizer that does not drop white
space is given whole texts.)  A rolling hash over the ids cuts each document
into chunks, so equal passages give equal chunks wherever they stand; a chunk is
named by its digest and stored once.  Recipes list the chunks of each document
in ascending document order with its first position; each recipe file carries a
Merkle root over its documents, and the manifest a root over the files.  Reading verifies
both the roots and the chunks.

Layout below the store's path (Parquet, written by Spark's commit protocol):
``chunks`` (digest, n, payload = zstandard of little-endian ids of ``width``
bytes), ``recipes`` (file, doc_id, start, n_tokens, chunks), ``manifest`` (file,
n_docs, n_tokens, merkle).

Defined results: a null text is empty and holds the end id alone; null ids come
first, repeated ids each keep their rows, in the order of a hash of their chunks; an empty table
gives an empty store.
"""

from __future__ import annotations

import hashlib
import json
import os
import unicodedata
import zlib
from array import array
from collections.abc import Iterable, Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..session import shipped
from .common import fresh_path, release_memory, settle

#: Ids in the window of the rolling hash, and the least, usual and most ids of a chunk.
ROLL, LEAST, USUAL, MOST = 16, 64, 1024, 8192
#: Digests of chunks a task remembers, so as not to send them twice.
SEEN_CHUNKS = 400_000
#: Bytes of text whose words are made distinct at once.
SLICE_BYTES = 1 << 24
END_ID = 2
_MIX = np.uint64(0x9E3779B97F4A7C15)


# ---------------------------------------------------------------- encoding
class WordEncoder:
    """Ids of whole texts.

    A slice of texts is cut into words and these into distinct ones by Arrow's
    kernels; each distinct word of the slice is encoded once.  Nothing is kept from
    slice to slice, so a worker's memory is bounded by the slice.
    """

    def __init__(self, path: str) -> None:
        os.environ["TOKENIZERS_PARALLELISM"] = "false"  # the tasks of an executor share its cores
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.by_word = drops_space(json.loads(self.tokenizer.to_str()))
        self.marks = {m: self._ids([m])[0] for m in (b".", b",")} if self.by_word else {}
        self.model = self.tokenizer.model if self.by_word and letters_are_one(json.loads(self.tokenizer.to_str())) else None

    def _plain(self, word: bytes) -> bytes | None:
        """Ids of a word of lower-case Latin letters straight from the model, which gets it unchanged; None for other words."""
        if self.model is None or not word:
            return None
        if word.isascii():
            if not (word.isalpha() and word.islower()):
                return None
            said = word.decode()
        else:
            try:
                said = word.decode()
            except UnicodeDecodeError:
                return None
            if not (said.isalpha() and said.islower() and max(said) < "\u0250" and unicodedata.is_normalized("NFC", said)):
                return None
            said = word.decode("latin-1").translate(BYTE_LETTERS)
        return array("I", [t.id for t in self.model.tokenize(said)]).tobytes()

    def _ids(self, texts: list[bytes]) -> list[bytes]:
        found = self.tokenizer.encode_batch_fast([t.decode("utf-8", "replace") for t in texts], add_special_tokens=False)
        return [array("I", x.ids).tobytes() for x in found]

    def encode(self, texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all texts in a row, and how many each has."""
        if not self.by_word:
            own = [np.frombuffer(x, np.uint32) for x in self._ids(texts)]
            return np.concatenate(own) if own else np.empty(0, np.uint32), np.array([len(x) for x in own], np.int64)
        # A-Z are lower-cased by the tokenizer in any case; its special tokens are matched before that.
        lists = pc.ascii_split_whitespace(pa.array([t if b"<|" in t else t.lower() for t in texts], pa.binary()).cast(pa.string(), safe=False))
        words = lists.flatten().dictionary_encode()
        ids = self._distinct_ids(words.dictionary.cast(pa.binary()).to_pylist())
        flat = np.frombuffer(b"".join(ids), np.uint32)
        size = np.fromiter(map(len, ids), np.int32, len(ids)) // 4
        start = np.cumsum(size, dtype=np.int32) - size
        index = words.indices.to_numpy(zero_copy_only=False)
        per_word = size[index]
        ends = np.cumsum(per_word, dtype=np.int32)
        place = np.repeat(start[index] - (ends - per_word), per_word)
        place += np.arange(len(place), dtype=np.int32)
        out = flat[place]
        bounds = np.concatenate(([0], ends))[lists.offsets.to_numpy() - lists.offsets[0].as_py()]
        del lists, words, ids, flat, index, per_word, place
        return out, np.diff(bounds)

    def _distinct_ids(self, words: list[bytes]) -> list[bytes]:
        """Ids of each of some distinct words."""
        known: dict[bytes, bytes | None] = {}
        out: list[bytes] = []
        rest: list[tuple[int, bytes, bytes]] = []
        for w in words:
            # A full stop or comma after a letter or digit is a token of its own.
            core, mark = (w[:-1], w[-1:]) if w[-1:] in self.marks and w[-2:-1].isalnum() else (w, b"")
            ids = known.get(core)
            if ids is None:
                known[core] = ids = self._plain(core)
            if ids is None:
                rest.append((len(out), core, mark))
                out.append(b"")
            else:
                out.append(ids + self.marks[mark] if mark else ids)
        cores = list({core for _, core, _ in rest})
        known = dict(zip(cores, self._ids(cores), strict=True))
        for i, core, mark in rest:
            out[i] = known[core] + self.marks[mark] if mark else known[core]
        return out


def drops_space(spec: dict) -> bool:
    """True if ids of a text are those of its white-space-separated words in order.

    That holds where the first pre-tokenizer keeps only matches of a pattern that
    never takes white space, and no normalizer, added token or model option looks beyond them.
    """
    pre = spec.get("pre_tokenizer") or {}
    first = pre.get("pretokenizers", [pre])[0]
    known = {"NFC", "Replace", "Lowercase"}
    normal = spec.get("normalizer") or {"type": "Sequence", "normalizers": []}
    parts = normal.get("normalizers", [normal])
    return (
        first.get("type") == "Split" and first.get("behavior") == "Removed" and bool(first.get("invert")) and r"[^\s\p{L}\p{N}]+" in first["pattern"].get("Regex", "")
        and all(p["type"] in known and (p["type"] != "Replace" or p["pattern"].get("Regex") == r"\s+" and p["content"] == " ") for p in parts)
        and not any(t["lstrip"] or t["rstrip"] or any(c.isspace() for c in t["content"]) for t in spec.get("added_tokens", []))
    )


def _byte_letters() -> dict[int, str]:
    """Byte to the letter that stands for it at byte level: itself if it prints, else the next letter from U+0100."""
    prints = {*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)}
    rest = iter(range(0x100, 0x200))
    return {b: chr(b if b in prints else next(rest)) for b in range(256)}


BYTE_LETTERS = _byte_letters()


def letters_are_one(spec: dict) -> bool:
    """True if a run of letters is one pre-token that the model gets byte by byte as letters."""
    parts = (spec.get("pre_tokenizer") or {}).get("pretokenizers", [])
    return (
        len(parts) == 2 and r"[\p{L}]+" in parts[0]["pattern"].get("Regex", "") and parts[1].get("type") == "ByteLevel"
        and not parts[1].get("add_prefix_space") and not parts[1].get("use_regex") and spec["model"].get("type") == "BPE"
    )


@lru_cache(maxsize=2)
def encoder(path: str) -> WordEncoder:
    return WordEncoder(path)


# ---------------------------------------------------------------- chunks
def rolling(ids: np.ndarray) -> np.ndarray:
    """Hash of the ``ROLL`` ids that end at each place (shorter at the start)."""
    h = (ids.astype(np.uint64) + np.uint64(1)) * _MIX
    h ^= h >> np.uint64(29)
    step, factor = 1, 0xBF58476D1CE4E5B9
    while step < ROLL:
        shifted = np.zeros_like(h)
        shifted[step:] = h[:-step]
        h = h + shifted * np.uint64(factor)
        factor = factor * factor & 0xFFFFFFFFFFFFFFFF
        step *= 2
    return h ^ (h >> np.uint64(31))


def cut(ids: np.ndarray) -> list[int]:
    """Ends of the chunks of one document."""
    n = len(ids)
    if n <= LEAST:
        return [n]
    marks = (np.flatnonzero((rolling(ids) % np.uint64(USUAL)) == 0) + 1).tolist()
    ends, start = [], 0
    for m in [*marks, n]:
        while m - start > MOST:
            start += MOST
            ends.append(start)
        if m - start >= LEAST:
            ends.append(m)
            start = m
    if not ends or ends[-1] < n:
        if ends and n - ends[-1] < LEAST and n - (ends[-2] if len(ends) > 1 else 0) <= MOST:
            ends.pop()
        ends.append(n)
    return ends


def digest_of(ids: bytes) -> bytes:
    return hashlib.blake2b(ids, digest_size=16).digest()


_ROWS = pa.schema(
    [("kind", pa.string()), ("spread", pa.int64()), ("doc_id", pa.int64()), ("n_tokens", pa.int64()), ("chunks", pa.list_(pa.struct([("digest", pa.binary()), ("n", pa.int64())]))), ("digest", pa.binary()), ("n", pa.int64()), ("payload", pa.binary())]
)
_ROWS_DDL = "kind string, spread long, doc_id long, n_tokens long, chunks array<struct<digest:binary,n:long>>, digest binary, n long, payload binary"


def slices(texts: pa.Array) -> Iterator[tuple[int, int]]:
    """(first row, rows) of runs with about ``SLICE_BYTES`` of text."""
    size = np.array([len(x.as_buffer()) if x.is_valid else 0 for x in texts], np.int64)
    group = np.cumsum(size) // SLICE_BYTES
    starts = np.flatnonzero(np.concatenate(([True], group[1:] != group[:-1]))).tolist() if len(size) else []
    yield from zip(starts, np.diff([*starts, len(size)]).tolist(), strict=True)


def _encode_rows(docs: DataFrame, tokenizer: str, end_id: int, width: int) -> DataFrame:
    tail, kind = np.array([end_id], "<u4").tobytes(), np.dtype(f"<u{width}")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import zstandard

        coder, press, seen = encoder(tokenizer), zstandard.ZstdCompressor(level=1), set()
        for batch in batches:
            recipes: dict[str, list] = {"id": [], "n": [], "chunks": [], "spread": []}
            packed: dict[str, list] = {"digest": [], "n": [], "payload": [], "spread": []}
            texts = batch.column(1)
            for lo, n_rows in slices(texts):
                flat, counts = coder.encode([x or b"" for x in texts.slice(lo, n_rows).to_pylist()])
                ends_at = np.cumsum(counts).tolist()
                for i, doc in enumerate(batch.column(0).slice(lo, n_rows).to_pylist()):
                    raw = flat[ends_at[i - 1] if i else 0 : ends_at[i]].astype("<u4").tobytes() + tail
                    ids = np.frombuffer(raw, "<u4")
                    own, start = [], 0
                    for end in cut(ids):
                        name = digest_of(raw[4 * start : 4 * end])
                        own.append({"digest": name, "n": end - start})
                        if name not in seen:
                            if len(seen) > SEEN_CHUNKS:
                                seen.clear()
                            seen.add(name)
                            packed["digest"].append(name)
                            packed["n"].append(end - start)
                            packed["payload"].append(press.compress(ids[start:end].astype(kind).tobytes()))
                            packed["spread"].append(int.from_bytes(name[:8], "little", signed=True))
                        start = end
                    recipes["id"].append(doc)
                    recipes["n"].append(len(ids))
                    recipes["chunks"].append(own)
                    recipes["spread"].append(int.from_bytes(own[0]["digest"][:8], "little", signed=True) ^ hash((doc, len(recipes["id"]))))
            for name, n, cols in (
                ("recipe", len(recipes["id"]), {"spread": recipes["spread"], "doc_id": recipes["id"], "n_tokens": recipes["n"], "chunks": recipes["chunks"]}),
                ("chunk", len(packed["n"]), {"spread": packed["spread"], "digest": packed["digest"], "n": packed["n"], "payload": packed["payload"]}),
            ):
                if n:
                    yield pa.RecordBatch.from_arrays([pa.array([name] * n) if f.name == "kind" else pa.array(cols[f.name], f.type) if f.name in cols else pa.nulls(n, f.type) for f in _ROWS], schema=_ROWS)
            del recipes, packed, texts
            release_memory()

    return shipped(docs).mapInArrow(run, _ROWS_DDL)


# ---------------------------------------------------------------- writing
def merkle_push(stack: list[tuple[int, bytes]], node: bytes) -> None:
    """Add a leaf to a tree of which only the complete parts are held, each with its height."""
    height = 0
    while stack and stack[-1][0] == height:
        node = hashlib.sha256(stack.pop()[1] + node).digest()
        height += 1
    stack.append((height, node))


def merkle_top(stack: list[tuple[int, bytes]]) -> bytes:
    """The root; an odd node moves up as it is."""
    if not stack:
        return hashlib.sha256(b"").digest()
    root = stack[-1][1]
    for _, node in reversed(stack[:-1]):
        root = hashlib.sha256(node + root).digest()
    return root


def merkle_root(leaves: Iterable[bytes]) -> bytes:
    """Root over the leaves, in order."""
    stack: list[tuple[int, bytes]] = []
    for leaf in leaves:
        merkle_push(stack, leaf)
    return merkle_top(stack)


def _leaves(recipes: DataFrame) -> DataFrame:
    """``file, start, n_tokens, leaf`` of each recipe: the digest of its id, length and chunk names."""
    head = F.concat_ws(",", F.coalesce(F.col("doc_id").cast("string"), F.lit("null")), F.col("n_tokens").cast("string"))
    names = F.array_join(F.transform("chunks", lambda c: F.hex(c["digest"])), "")
    return recipes.select("file", "start", "n_tokens", F.unhex(F.sha2(F.concat_ws(":", head, names), 256)).alias("leaf"))


def _file_roots(recipes: DataFrame) -> DataFrame:
    """One row per recipe file: its number, documents, ids and Merkle root over its leaves in file order."""
    parts = max(1, int(recipes.sparkSession.conf.get("spark.sql.shuffle.partitions")))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        trees: dict[int, list[tuple[int, bytes]]] = {}
        docs: dict[int, int] = {}
        totals: dict[int, int] = {}
        for batch in batches:
            for file, n, leaf in zip(*(batch.column(c).to_pylist() for c in ("file", "n_tokens", "leaf")), strict=True):
                merkle_push(trees.setdefault(file, []), leaf)
                docs[file] = docs.get(file, 0) + 1
                totals[file] = totals.get(file, 0) + n
        if trees:
            yield pa.RecordBatch.from_arrays(
                [pa.array(list(trees), pa.int64()), pa.array([docs[k] for k in trees], pa.int64()), pa.array([totals[k] for k in trees], pa.int64()), pa.array([merkle_top(x) for x in trees.values()], pa.binary())],
                ["file", "n_docs", "n_tokens", "merkle"],
            )

    return _leaves(recipes).repartition(parts, "file").sortWithinPartitions("file", "start").mapInArrow(run, "file long, n_docs long, n_tokens long, merkle binary")


def write_store(docs: DataFrame, path: str, tokenizer: str, end_id: int = END_ID, width: int | None = None) -> str:
    """Encode ``doc_id, text`` and write the store; one shuffle, in which every chunk moves once per task at most."""
    spark = docs.sparkSession
    if width is None:
        from tokenizers import Tokenizer

        width = 2 if Tokenizer.from_file(tokenizer).get_vocab_size() <= 65_536 else 4
    rows = _encode_rows(docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("binary").alias("text")), tokenizer, end_id, width)
    first = F.row_number().over(Window.partitionBy("spread", "digest").orderBy("n"))
    parts = max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))
    dealt = rows.repartition(parts, "spread").withColumn("_first", first).where("kind = 'recipe' or _first = 1")
    dealt.drop("_first", "spread").write.partitionBy("kind").parquet(f"{path}/rows")
    whole = spark.read.schema("doc_id long, n_tokens long, chunks array<struct<digest:binary,n:long>>, digest binary, n long, payload binary, kind string").parquet(f"{path}/rows")
    order = [F.col("doc_id").asc_nulls_first(), F.xxhash64("chunks")]
    sorted_ = whole.where("kind = 'recipe'").select("doc_id", "n_tokens", "chunks").repartitionByRange(parts, *order).sortWithinPartitions(*order)
    sorted_.select(F.spark_partition_id().cast("long").alias("file"), F.monotonically_increasing_id().alias("place"), "*").write.parquet(f"{path}/placed")
    placed = spark.read.schema("file long, place long, doc_id long, n_tokens long, chunks array<struct<digest:binary,n:long>>").parquet(f"{path}/placed")
    # One number per file goes to the driver: files are as many as partitions.
    totals, before = {}, 0
    for r in sorted(placed.groupBy("file").agg(F.sum("n_tokens").alias("n")).collect(), key=lambda r: r["file"]):
        totals[r["file"]], before = before, before + r["n"]
    base = F.broadcast(spark.createDataFrame(list(totals.items()), "file long, base long"))
    running = F.sum("n_tokens").over(Window.partitionBy("file").orderBy("place").rowsBetween(Window.unboundedPreceding, -1))
    recipes = placed.join(base, "file").select("file", "doc_id", (F.col("base") + F.coalesce(running, F.lit(0))).alias("start"), "n_tokens", "chunks")
    recipes.write.parquet(f"{path}/recipes")
    _file_roots(recipes).withColumn("width", F.lit(width)).write.parquet(f"{path}/manifest")
    return path


# ---------------------------------------------------------------- reading
def read_recipes(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema("file long, doc_id long, start long, n_tokens long, chunks array<struct<digest:binary,n:long>>").parquet(f"{path}/recipes")


def read_chunks(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema("doc_id long, n_tokens long, digest binary, n long, payload binary, kind string").parquet(f"{path}/rows").where("kind = 'chunk'").select("digest", "n", "payload")


def read_manifest(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema("file long, n_docs long, n_tokens long, merkle binary, width int").parquet(f"{path}/manifest")


@lru_cache(maxsize=1)
def _opener():  # noqa: ANN202
    import zstandard

    return zstandard.ZstdDecompressor()


def _unpack(payload: bytes, width: int) -> np.ndarray:
    return np.frombuffer(_opener().decompress(payload), np.dtype(f"<u{width}")).astype("<u4")


def store_width(spark: SparkSession, path: str) -> int:
    row = read_manifest(spark, path).select("width").first()
    return row["width"] if row else 4


def read_documents(spark: SparkSession, path: str) -> DataFrame:
    """``doc_id, start, ids`` rebuilt from recipes and chunks."""
    width = store_width(spark, path)
    parts = read_recipes(spark, path).select("start", "doc_id", F.posexplode("chunks").alias("at", "c")).select("start", "doc_id", "at", F.col("c.digest").alias("digest"))
    held = parts.join(read_chunks(spark, path), "digest")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids = [np.concatenate([_unpack(p["payload"], width) for p in row]) for row in batch.column("parts").to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("start"), pa.array([x.astype(np.int64) for x in ids], pa.list_(pa.int64()))], ["doc_id", "start", "ids"])

    whole = held.groupBy("doc_id", "start").agg(F.array_sort(F.collect_list(F.struct("at", "payload"))).alias("parts"))
    return shipped(whole).mapInArrow(run, "doc_id long, start long, ids array<long>")


def check_chunks(spark: SparkSession, path: str) -> DataFrame:
    """``digest, n, crc`` of every stored chunk as read; a chunk that does not match its digest raises."""
    width = store_width(spark, path)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            crcs, sizes = [], []
            for name, payload in zip(batch.column("digest").to_pylist(), batch.column("payload").to_pylist(), strict=True):
                raw = _unpack(payload, width).tobytes()
                if digest_of(raw) != name:
                    raise ValueError(f"chunk {name.hex()} is damaged")
                crcs.append(zlib.crc32(raw))
                sizes.append(len(raw) // 4)
            yield pa.RecordBatch.from_arrays([batch.column("digest"), pa.array(sizes, pa.int64()), pa.array(crcs, pa.int64())], ["digest", "n", "crc"])

    return read_chunks(spark, path).mapInArrow(run, "digest binary, n long, crc long")


#: The polynomial of CRC-32, reflected.
_CRC_POLY = 0xEDB88320


def _times(a: int, b: int) -> int:
    """Product of two reflected polynomials modulo that of CRC-32."""
    out = 0
    for _ in range(32):
        if a & 0x80000000:
            out ^= b
        a = a << 1 & 0xFFFFFFFF
        b = b >> 1 ^ (_CRC_POLY if b & 1 else 0)
    return out


@lru_cache(maxsize=65_536)
def _shift(n_bytes: int) -> int:
    """x to the power of eight times the bytes."""
    out, square, n = 0x80000000, 0x00800000, n_bytes
    while n:
        if n & 1:
            out = _times(out, square)
        square = _times(square, square)
        n >>= 1
    return out


def join_many(at: np.ndarray, crcs: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """CRCs of many concatenations at once; ``at`` are the bounds of each one's parts."""
    out = crcs[at[:-1]].astype(np.uint32)
    count, k = np.diff(at), 1
    while (live := np.flatnonzero(count > k)).size:
        part = at[live] + k
        a, b = out[live], np.fromiter(map(_shift, sizes[part].tolist()), np.uint32, len(live))
        product = np.zeros(len(live), np.uint32)
        for _ in range(32):
            product ^= np.where(a & np.uint32(0x80000000), b, np.uint32(0))
            a = a << np.uint32(1)
            b = (b >> np.uint32(1)) ^ np.where(b & np.uint32(1), np.uint32(_CRC_POLY), np.uint32(0))
        out[live] = product ^ crcs[part].astype(np.uint32)
        k += 1
    return out


def join_crcs(parts: list[tuple[int, int]]) -> int:
    """CRC-32 of the concatenation of parts given by CRC and length in bytes."""
    crc = parts[0][0]
    for c, n in parts[1:]:
        crc = _times(crc, _shift(n)) ^ c
    return crc


def check_recipes(spark: SparkSession, path: str) -> None:
    """Recompute the Merkle root of every recipe file as read; raises ValueError if the manifest says otherwise."""
    told = read_manifest(spark, path).select("file", "n_docs", "n_tokens", "merkle")
    both = settle(_file_roots(read_recipes(spark, path)), "roots").withColumn("side", F.lit(1)).unionByName(told.withColumn("side", F.lit(2)))
    wrong = both.groupBy("file", "n_docs", "n_tokens", "merkle").agg(F.sum("side").alias("sides")).where("sides <> 3").select("file").first()
    if wrong is not None:
        raise ValueError(f"recipe file {wrong['file']} does not match the manifest")


def document_digests(spark: SparkSession, path: str) -> DataFrame:
    """``doc_id, start, n_tokens, ids_crc32`` of every document, read back chunk by chunk.

    The recipes are verified against the manifest first.  Each stored chunk is read, verified and summed once;
    documents then join the sums of their chunks, so no payload is shuffled again.  A document with a missing
    chunk, or with another length than its recipe says, raises.
    """
    check_recipes(spark, path)
    parts = read_recipes(spark, path).select("doc_id", "start", "n_tokens", F.posexplode("chunks").alias("at", "c")).select("doc_id", "start", "n_tokens", "at", F.col("c.digest").alias("digest"))
    held = parts.join(settle(check_chunks(spark, path), "sums"), "digest", "left")
    whole = held.groupBy("doc_id", "start", "n_tokens").agg(F.array_sort(F.collect_list(F.struct("at", F.coalesce("n", F.lit(-1)).alias("n"), F.coalesce("crc", F.lit(0)).alias("crc")))).alias("parts"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            lists = batch.column("parts")
            at = lists.offsets.to_numpy() - lists.offsets[0].as_py()
            n, crc = (lists.flatten().field(c).to_numpy() for c in ("n", "crc"))
            sizes = np.diff(np.concatenate(([0], np.cumsum(n)))[at])
            wrong = np.flatnonzero(sizes != batch.column("n_tokens").to_numpy())
            if len(wrong) or (n < 0).any():
                raise ValueError(f"{max(1, len(wrong))} documents do not have the ids their recipes say")
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("start"), pa.array(sizes), pa.array(join_many(at, crc, 4 * n).astype(np.int64))], ["doc_id", "start", "n_tokens", "ids_crc32"])

    return shipped(whole).mapInArrow(run, "doc_id long, start long, n_tokens long, ids_crc32 long")


def verify(spark: SparkSession, path: str) -> bool:
    """True if every chunk matches its digest (else it raises) and every recipe file its Merkle root."""
    check_chunks(spark, path).agg(F.count("*")).collect()
    try:
        check_recipes(spark, path)
    except ValueError:
        return False
    return True


def store_root(spark: SparkSession, path: str) -> str:
    """Root over the recipe files, as hexadecimal digits."""
    return merkle_root([bytes(r["merkle"]) for r in read_manifest(spark, path).orderBy("file").select("merkle").collect()]).hex()


def default_tokenizer() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def stage(docs: DataFrame, tokenizer: str | None = None) -> DataFrame:
    """Write the documents as a store and return what reading it back gives."""
    path = write_store(docs, fresh_path(docs.sparkSession, "tokens"), tokenizer or default_tokenizer())
    return document_digests(docs.sparkSession, path)
