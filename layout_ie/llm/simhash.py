"""SimHash fingerprints and near-duplicate components by a Gray-order hierarchical index.

Two fingerprints that differ in at most ``radius`` of 64 bits agree on at least
``blocks - radius`` of ``blocks`` bit blocks, so every pair meets in the bucket
of some block choice.  The rows (bucket, fingerprint) are sorted by bucket and
Gray rank and dealt out by range, so a hot bucket spreads over many tasks.
Inside a task runs of neighbours form leaves; each leaf factors out the bits
that all its members share, upper nodes factor out those of their leaves, and a
pair of nodes is left out as soon as the differences of their shared bits exceed
the radius.  Nodes of a bucket that goes over a task's border are written and
paired by their shared bits in the same way.  Each task reduces its links to
a spanning forest, so no group emits all its pairs; components of the forest
come from rounds of star contraction on DataFrames.  The same search serves the
pipeline's near-copy stage (``near_copies``).

Defined results: a null or wordless text has fingerprint zero and is linked like
any other; a null doc_id gets a fingerprint and a null component; repeated ids
keep their rows; empty tables give empty results.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import shipped
from .common import drop_written, settle

SEED = 42
SHINGLE = 4
RADIUS = 4
BLOCKS = 6
#: Members of a leaf and children of an upper node.
LEAF, FAN = 32, 16


# ---------------------------------------------------------------- fingerprints
def shingle_hashes(text: bytes | None, size: int = SHINGLE, seed: int = SEED) -> np.ndarray:
    """XXH64 of every run of ``size`` words, repeats included; of all words if there are fewer."""
    import xxhash

    words = (text or b"").lower().split()
    if not words:
        return np.empty(0, np.uint64)
    joined = b" ".join(words)
    if len(words) <= size:
        return np.array([xxhash.xxh64_intdigest(joined, seed)], np.uint64)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1)
    starts = np.concatenate(([0], ends[: len(words) - size])).tolist()
    digest = xxhash.xxh64_intdigest
    return np.array([digest(joined[a:b], seed) for a, b in zip(starts, (ends[size - 1 :] - 1).tolist(), strict=True)], np.uint64)


def majority(hashes: np.ndarray) -> int:
    """Bits that are set in over half of the hashes."""
    n = len(hashes)
    if not n:
        return 0
    counts = np.zeros(64, np.int64)
    for at in range(0, n, 4096):
        bits = np.unpackbits(hashes[at : at + 4096].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
        counts += bits.sum(axis=0, dtype=np.int32)
    return int(np.packbits(2 * counts > n, bitorder="little").view(np.uint64)[0])


def fingerprints(docs: DataFrame, text: str = "text", keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """``keep`` and ``fp`` (64 bits as a signed long) of each whole text."""
    rows = docs.select(*keep, F.col(text).cast("binary").alias("_text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            values = [majority(shingle_hashes(x.as_py())) for x in batch.column(len(keep))]
            fp = pa.array(np.array(values, np.uint64).view(np.int64))
            yield pa.RecordBatch.from_arrays([*batch.columns[: len(keep)], fp], [*keep, "fp"])

    schema = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.select(*keep).schema), "fp long"])
    return shipped(rows).mapInArrow(run, schema)


def fp_hex(column):  # noqa: ANN001, ANN201
    """16 lower-case hex digits of a signed 64-bit column."""
    return F.lower(F.lpad(F.hex(column), 16, "0"))


# ---------------------------------------------------------------- index
def gray_rank(bits: np.ndarray) -> np.ndarray:
    """Place of each word in the reflected Gray sequence."""
    rank = bits.copy()
    for shift in (1, 2, 4, 8, 16, 32):
        rank ^= rank >> np.uint64(shift)
    return rank


def gray_rank_column(fp):  # noqa: ANN001, ANN201
    """The same on the JVM, shifted so that signed order is unsigned order."""
    for shift in (1, 2, 4, 8, 16, 32):
        fp = fp.bitwiseXOR(F.shiftrightunsigned(fp, shift))
    return fp.bitwiseXOR(F.lit(-(2**63)).cast("long"))


def block_masks(blocks: int = BLOCKS, radius: int = RADIUS) -> list[int]:
    """One mask for each choice of ``blocks - radius`` blocks."""
    edges = [round(64 * i / blocks) for i in range(blocks + 1)]
    own = [((1 << (b - a)) - 1) << a for a, b in zip(edges, edges[1:], strict=False)]
    return [sum(pick) for pick in combinations(own, blocks - radius)]


def shared_bits(fps: np.ndarray, cuts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Mask of the bits on which each run agrees, and their pattern."""
    ones, any_ = np.bitwise_and.reduceat(fps, cuts), np.bitwise_or.reduceat(fps, cuts)
    mask = ~(ones ^ any_)
    return mask, ones & mask


def close_nodes(ma: np.ndarray, pa_: np.ndarray, mb: np.ndarray, pb: np.ndarray, radius: int) -> np.ndarray:
    return np.bitwise_count((pa_ ^ pb) & ma & mb) <= radius


def roots(u: np.ndarray, v: np.ndarray, n: int) -> np.ndarray:
    """Smallest index of the component of each of ``n`` indices."""
    label = np.arange(n)
    while len(u):
        low = np.minimum(label[u], label[v])
        np.minimum.at(label, label[u], low)
        np.minimum.at(label, label[v], low)
        while (deeper := label[label]).tobytes() != label.tobytes():
            label = deeper
        open_ = label[u] != label[v]
        u, v = u[open_], v[open_]
    return label


def _pairs_between(a0: int, a1: int, b0: int, b1: int) -> tuple[np.ndarray, np.ndarray]:
    left, right = np.meshgrid(np.arange(a0, a1), np.arange(b0, b1), indexing="ij")
    return left.ravel(), right.ravel()


def index_links(fps: np.ndarray, radius: int = RADIUS, other: np.ndarray | None = None) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Links among fingerprints in Gray order (or with those of ``other``), searched top-down.

    A leaf whose members differ in ``radius`` bits at most is linked as a whole.
    """
    sides = []
    for side in (fps, other if other is not None else fps):
        leaf_cuts = np.arange(0, len(side), LEAF)
        mask, pattern = shared_bits(side, leaf_cuts)
        top_cuts = np.arange(0, len(leaf_cuts), FAN)
        ones = np.bitwise_and.reduceat(pattern, top_cuts)
        any_ = np.bitwise_or.reduceat(pattern, top_cuts)
        top_mask = np.bitwise_and.reduceat(mask, top_cuts) & ~(ones ^ any_)
        sides.append((side, leaf_cuts, mask, pattern, top_cuts, top_mask, ones & top_mask))
    (fa, ca, ma, pa_, ta, tma, tpa), (fb, cb, mb, pb, tb, tmb, tpb) = sides
    for i in range(len(ta)):
        first = i if other is None else 0
        for j in (np.flatnonzero(close_nodes(tma[i], tpa[i], tmb[first:], tpb[first:], radius)) + first).tolist():
            la, lb = _pairs_between(ta[i], min(ta[i] + FAN, len(ca)), tb[j], min(tb[j] + FAN, len(cb)))
            if other is None:
                la, lb = la[la <= lb], lb[la <= lb]
            near = close_nodes(ma[la], pa_[la], mb[lb], pb[lb], radius)
            la, lb = la[near], lb[near]
            if not len(la):
                continue
            left = (ca[la][:, None] + np.repeat(np.arange(LEAF), LEAF)[None, :]).ravel()
            right = (cb[lb][:, None] + np.tile(np.arange(LEAF), LEAF)[None, :]).ravel()
            ok = (left < len(fa)) & (right < len(fb))
            if other is None:
                ok &= left < right
            left, right = left[ok], right[ok]
            hit = np.bitwise_count(fa[left] ^ fb[right]) <= radius
            if hit.any():
                yield left[hit], right[hit]


def bucket_forest(bucket: np.ndarray, fps: np.ndarray, radius: int = RADIUS) -> np.ndarray:
    """Component root (an index) of each row, rows sorted by bucket and Gray rank, links within buckets only."""
    n = len(fps)
    label = np.arange(n)
    # Neighbours up to a leaf apart, all buckets at once.
    us, vs = [], []
    for d in range(1, min(LEAF, n)):
        same = np.flatnonzero(bucket[d:] == bucket[:-d])
        if not len(same):
            break
        hit = same[np.bitwise_count(fps[same] ^ fps[same + d]) <= radius]
        us.append(hit)
        vs.append(hit + d)
    if us:
        label = roots(np.concatenate(us), np.concatenate(vs), n)
    # Buckets longer than a leaf go through the hierarchy.
    starts = np.flatnonzero(np.concatenate(([True], bucket[1:] != bucket[:-1]))) if n else np.empty(0, np.int64)
    ends = np.append(starts[1:], n)
    for a, b in zip(starts[ends - starts > LEAF].tolist(), ends[ends - starts > LEAF].tolist(), strict=True):
        for u, v in index_links(fps[a:b], radius):
            open_ = label[u + a] != label[v + a]
            if open_.any():
                label = label[roots(label[u[open_] + a], label[v[open_] + a], n)]
    return label


_FOREST = pa.schema([("a", pa.int64()), ("b", pa.int64()), ("bucket", pa.int64()), ("chunk", pa.int64()), ("mask", pa.int64()), ("pattern", pa.int64()), ("fps", pa.binary()), ("nodes", pa.binary())])
_FOREST_DDL = "a long, b long, bucket long, chunk long, mask long, pattern long, fps binary, nodes binary"
#: Members of one written node of a bucket that goes over a task's border.
CHUNK = 1024


def _forest_rows(child: np.ndarray, root: np.ndarray) -> pa.RecordBatch:
    rows = len(child)
    return pa.RecordBatch.from_arrays([pa.array(child), pa.array(root), *(pa.nulls(rows, f.type) for f in list(_FOREST)[2:])], schema=_FOREST)


def link_buckets(rows: DataFrame, radius: int = RADIUS) -> DataFrame:
    """``bucket, rank, fp, node`` in, sorted within partitions: forest edges, and the nodes at partition borders."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept = [b for b in batches if b.num_rows]
        if not kept:
            return
        table = pa.Table.from_batches(kept)
        bucket, fps, node = (table.column(c).to_numpy() for c in ("bucket", "fp", "node"))
        fps = fps.view(np.uint64) if fps.flags["C_CONTIGUOUS"] else np.ascontiguousarray(fps).view(np.uint64)
        label = bucket_forest(bucket, fps, radius)
        moved = np.flatnonzero(label != np.arange(len(label)))
        yield _forest_rows(node[moved], node[label[moved]])
        for edge in dict.fromkeys((int(bucket[0]), int(bucket[-1]))):
            at = np.flatnonzero(bucket == edge)
            for lo in range(0, len(at), CHUNK):
                part = at[lo : lo + CHUNK]
                mask, pattern = shared_bits(fps[part], np.array([0]))
                yield pa.RecordBatch.from_arrays(
                    [pa.nulls(1, pa.int64()), pa.nulls(1, pa.int64()), pa.array([edge]), pa.array([int(node[part[0]])]), pa.array(mask.view(np.int64)), pa.array(pattern.view(np.int64)), pa.array([fps[part].tobytes()]), pa.array([node[part].tobytes()])],
                    schema=_FOREST,
                )

    return shipped(rows).mapInArrow(run, _FOREST_DDL)


def link_borders(nodes: DataFrame, radius: int = RADIUS) -> DataFrame:
    """Links between the written nodes of one bucket that lie in different tasks."""
    left = nodes.select("bucket", *(F.col(c).alias(f"{c}_l") for c in ("chunk", "mask", "pattern", "fps", "nodes")))
    right = nodes.select("bucket", *(F.col(c).alias(f"{c}_r") for c in ("chunk", "mask", "pattern", "fps", "nodes")))
    shared = F.col("mask_l").bitwiseAND(F.col("mask_r"))
    apart = F.bit_count(F.col("pattern_l").bitwiseXOR(F.col("pattern_r")).bitwiseAND(shared))
    pairs = left.join(right, "bucket").where((F.col("chunk_l") < F.col("chunk_r")) & (apart <= radius)).select("fps_l", "nodes_l", "fps_r", "nodes_r")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for fl, nl, fr, nr in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                a, b = np.frombuffer(fl, np.uint64), np.frombuffer(fr, np.uint64)
                found = list(index_links(a, radius, b))
                if found:
                    u, v = (np.concatenate(x) for x in zip(*found, strict=True))
                    node = np.concatenate((np.frombuffer(nl, np.int64), np.frombuffer(nr, np.int64)))
                    label = roots(u, v + len(a), len(node))
                    moved = np.flatnonzero(label != np.arange(len(label)))
                    yield pa.RecordBatch.from_arrays([pa.array(node[moved]), pa.array(node[label[moved]])], ["a", "b"])

    return shipped(pairs).mapInArrow(run, "a long, b long")


# ---------------------------------------------------------------- components
def components(edges: DataFrame, rows: int | None = None) -> DataFrame:
    """``node, root`` for every end of the edges ``a, b`` (about ``rows``); root is the smallest node reachable.

    Alternates large-star and small-star contraction; each round is a written
    table, so a lost executor costs one round.  No node's neighbours are gathered
    in a row: a group only ever yields its minimum.  The end is reached when all
    edges are stars: every child has one parent and no parent is a child.
    """
    e = settle(edges.where("a <> b").select(F.greatest("a", "b").alias("x"), F.least("a", "b").alias("y")).distinct(), "edges", rows)
    rows = e.count()
    while True:
        both = e.unionByName(e.select(F.col("y").alias("x"), F.col("x").alias("y")))
        # Written, so that the join reads both sides from exchanges and Spark may split the root of a large group.
        low = settle(both.groupBy("x").agg(F.min("y").alias("m")).select("x", F.least("x", "m").alias("m")), "low", 2 * rows)
        large = settle(both.where("y > x").join(low, "x").select(F.col("y").alias("x"), F.col("m").alias("y")).distinct(), "large", 2 * rows)
        drop_written(e)
        least = large.groupBy("x").agg(F.min("y").alias("m"))
        joined = large.join(least, "x")
        small = joined.where("y <> m").select(F.col("y").alias("x"), F.col("m").alias("y")).unionByName(least.select("x", F.col("m").alias("y"))).distinct()
        e = settle(small, "edges", 2 * rows)
        drop_written(low)
        drop_written(large)
        parents = e.select(F.col("y").alias("x"), F.lit(True).alias("parent")).distinct()
        if e.groupBy("x").agg(F.count("*").alias("n")).join(parents, "x", "left").where("n > 1 or parent").isEmpty():
            return e.select(F.col("x").alias("node"), F.col("y").alias("root"))


def forest(known: DataFrame, radius: int = RADIUS, blocks: int = BLOCKS) -> DataFrame:
    """Spanning edges ``a, b`` of the links among distinct fingerprints ``fp, node``, found by the index."""
    spark = known.sparkSession
    keys = F.array(*(F.struct(F.lit(i).alias("choice"), F.col("fp").bitwiseAND(F.lit(m - 2**64 if m >= 2**63 else m).cast("long")).alias("part")) for i, m in enumerate(block_masks(blocks, radius))))
    rows = known.select("fp", "node", F.explode(keys).alias("k")).select(
        F.xxhash64("k.choice", "k.part").alias("bucket"), "fp", "node", gray_rank_column(F.col("fp")).alias("rank")
    )
    parts = max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))
    linked = settle(link_buckets(rows.repartitionByRange(parts, "bucket", "rank").sortWithinPartitions("bucket", "rank"), radius), "forest")
    return linked.where("bucket is null").select("a", "b").unionByName(link_borders(linked.where("bucket is not null"), radius))


def cluster(prints: DataFrame, radius: int = RADIUS, blocks: int = BLOCKS) -> DataFrame:
    """``fp, node, root`` of each distinct fingerprint of ``doc_id, fp``: its smallest id and its component's."""
    known = settle(prints.where(F.col("doc_id").isNotNull()).groupBy("fp").agg(F.min("doc_id").alias("node")), "distinct")
    found = components(forest(known, radius, blocks))
    return known.join(found, "node", "left").select("fp", "node", F.coalesce("root", "node").alias("root"))


def near_duplicates(docs: DataFrame) -> DataFrame:
    """``doc_id, fingerprint, component_id`` for every row."""
    prints = settle(fingerprints(docs), "prints")
    named = cluster(prints).select("fp", "root")
    return prints.join(named, "fp", "left").select(
        "doc_id", fp_hex(F.col("fp")).alias("fingerprint"), F.when(F.col("doc_id").isNotNull(), F.col("root")).alias("component_id")
    )

