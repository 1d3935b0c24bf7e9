"""Temperature mixing of sources, realised as budgeted block permutations, as DataFrame expressions only.

A source with token share q gets weight q**a / Z.  The exponent a goes from 1
(natural shares) to 0 (equal shares); it is bisected, a ladder of exponents per
pass over the source totals, to the smallest value whose mix stays within the repetition
limit (``max_epochs``) and does not exceed a target entropy.  The budget is the
least for which every document is used at least once, so no row is lost: a source
with weight w has ``w * budget / tokens`` epochs, between 1 and the limit.

Within a source every epoch is one pass over a permutation by hash; the last,
broken pass takes the documents whose place in the permutation lies within the fraction
that is left.  The place of each copy of a document in the stream of its source gives the copy's block: each block
holds the same tokens of every source up to one document, in an order by hash.  Places come from
prefix sums over ``(source, slice of the permutation)``, so a hot source spreads
over all slices; slices grow in number with the rows.

Defined results: a null source is a source of its own; a null or wordless text
weighs nothing and is used once; repeated rows are rows of their own; an empty table gives
an empty plan.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import WORD_CHAR, WORD_GAP, settle, unused

MAX_EPOCHS = 4.0
#: Tokens of one block of the mix.
BLOCK_TOKENS = 1_000_000
#: Slices of a source's permutation, at least, and rows of the table that call for one more: a slice is summed up in one task.
SLICES, SLICE_ROWS = 256, 200_000
SEED = 11
#: Exponents tried in one pass, and passes.
RUNGS, PASSES = 32, 3
#: Broadcast the table of slices up to this number of rows.
BROADCAST_ROWS = 400_000


def count_tokens(text: Column) -> Column:
    """Words of the whole text."""
    return F.size(F.array_remove(F.split(F.coalesce(text, F.lit("")), WORD_GAP), "")).cast("long")


def _measures(totals: DataFrame, exponents: list[float]) -> list[tuple[float, float, float]]:
    """(exponent, entropy in nats, epochs of the most repeated source) of each exponent, in one pass."""
    share = F.col("share")
    sums = []
    for i, a in enumerate(exponents):
        sums += [F.sum(F.pow(share, F.lit(a))).alias(f"z{i}"), F.sum(F.pow(share, F.lit(a)) * F.log(share)).alias(f"s{i}"), F.max(F.pow(share, F.lit(a - 1))).alias(f"h{i}"), F.min(F.pow(share, F.lit(a - 1))).alias(f"l{i}")]
    import math

    row = totals.where("share > 0").agg(*sums).first()
    if row["z0"] is None:
        return []
    return [(a, math.log(row[f"z{i}"]) - a * row[f"s{i}"] / row[f"z{i}"], row[f"h{i}"] / row[f"l{i}"]) for i, a in enumerate(exponents)]


def find_exponent(totals: DataFrame, max_epochs: float = MAX_EPOCHS, entropy: float | None = None) -> float:
    """The smallest exponent in [0, 1] whose mix obeys the limits; both measures fall as it grows."""
    low, high = 0.0, 1.0
    for _ in range(PASSES):
        rungs = [low + (high - low) * i / RUNGS for i in range(RUNGS + 1)]
        found = _measures(totals, rungs)
        good = [a for a, h, e in found if e <= max_epochs * (1 + 1e-9) and (entropy is None or h <= entropy + 1e-9)]
        if not found or not good:
            return high
        high = min(good)
        if high == low:
            return high
        low = max(a for a in rungs if a < high)
    return high


def source_weights(totals: DataFrame, exponent: float) -> DataFrame:
    """Adds ``weight`` (sums to 1) and ``epochs`` (1 at least) to ``source, tokens, share``."""
    raw = F.when(F.col("share") > 0, F.pow("share", F.lit(exponent))).otherwise(0.0)
    pull = F.when(F.col("share") > 0, F.pow("share", F.lit(exponent - 1.0)))
    norms = totals.agg(F.sum(raw).alias("z"), F.min(pull).alias("least")).first()
    z, least = norms["z"] or 1.0, norms["least"] or 1.0
    return totals.select("source", "tokens", "share", (raw / F.lit(z)).alias("weight"), F.coalesce(F.greatest(pull / F.lit(least), F.lit(1.0)), F.lit(1.0)).alias("epochs"))


def _order(seed: int = SEED) -> Column:
    """A document's place in the permutation of its source."""
    return F.xxhash64("doc_id", "source", F.lit(seed))


def _slice(slices: int) -> Column:
    return F.pmod(F.shiftrightunsigned(_order(), 24), F.lit(slices))


def plan_slices(sized: DataFrame, max_epochs: float, entropy: float | None) -> tuple[DataFrame, int]:
    """``_source, _part, _before, _in, tokens, weight, epochs`` of each slice of each source, and the number of slices.

    Broadcast if it is small; ``_before`` are the tokens of the source's slices in front.
    """
    n_slices = max(SLICES, sized.count() // SLICE_ROWS)
    slices = settle(sized.groupBy("source", _slice(n_slices).alias("_slice")).agg(F.sum("n_tokens").alias("_in")), "slices")
    totals = slices.groupBy("source").agg(F.sum("_in").alias("tokens"))
    whole = totals.agg(F.sum("tokens")).first()[0] or 0
    totals = settle(totals.withColumn("share", F.col("tokens") / F.lit(float(max(whole, 1)))), "totals")
    weights = source_weights(totals, find_exponent(totals, max_epochs, entropy)).withColumnRenamed("source", "_of")
    w = Window.partitionBy("source").orderBy("_slice").rowsBetween(Window.unboundedPreceding, -1)
    bases = slices.withColumn("_before", F.coalesce(F.sum("_in").over(w), F.lit(0))).withColumnRenamed("source", "_source")
    bases = bases.join(weights, F.col("_source").eqNullSafe(F.col("_of"))).select("_source", F.col("_slice").alias("_part"), "_before", "_in", "tokens", "weight", "epochs")
    bases = settle(bases, "bases")
    return (F.broadcast(bases) if bases.count() <= BROADCAST_ROWS else bases), n_slices


def plan_mix(sized: DataFrame, max_epochs: float = MAX_EPOCHS, entropy: float | None = None, block_tokens: int = BLOCK_TOKENS, only_cut: tuple[DataFrame, int] | None = None) -> DataFrame:
    """``doc_id, source, n_tokens`` in (written rows); adds weight, epochs, copies, place and blocks.

    ``copies`` are the passes that use the document, ``place`` the tokens before
    it in its source's permutation, ``blocks`` the block of each copy.  ``only_cut`` (planned slices) leaves out
    the slices whose documents all have the same number of copies.
    """
    bases, n_slices = only_cut or plan_slices(sized, max_epochs, entropy)
    cut = (F.col("epochs") - F.floor("epochs")) * F.col("tokens")
    if only_cut:
        bases = bases.where((F.col("_before") < cut) & (F.col("_before") + F.col("_in") > cut))
    keyed = sized.withColumn("_order", _order()).withColumn("_slice", _slice(n_slices))
    placed = keyed.join(bases, F.col("source").eqNullSafe(F.col("_source")) & (F.col("_slice") == F.col("_part")))
    inner = Window.partitionBy("source", "_slice").orderBy("_order", "doc_id").rowsBetween(Window.unboundedPreceding, -1)
    placed = placed.withColumn("_here", F.coalesce(F.sum("n_tokens").over(inner), F.lit(0)))
    place = (F.col("_before") + F.col("_here")).cast("long")
    copies = F.when(F.col("n_tokens") == 0, F.lit(1)).otherwise(F.floor("epochs") + (place < cut).cast("long")).cast("long")
    quota = F.greatest(F.col("weight") * F.lit(float(block_tokens)), F.lit(1.0))
    # The k-th copy stands k whole passes further on.
    blocks = F.transform(F.sequence(F.lit(0).cast("long"), copies - 1), lambda k: F.floor((place + k * F.col("tokens")) / quota).cast("long"))
    return placed.select(*[c for c in sized.columns], "weight", "epochs", copies.alias("copies"), place.alias("place"), blocks.alias("blocks"))


def mix(docs: DataFrame, max_epochs: float = MAX_EPOCHS, entropy: float | None = None, block_tokens: int = BLOCK_TOKENS) -> DataFrame:
    """One row per row of ``docs`` with what the mix does with it."""
    sized = settle(docs.select("doc_id", "source", count_tokens(F.col("text")).alias("n_tokens")), "sized")
    return plan_mix(sized, max_epochs, entropy, block_tokens)


def block_stream(plan: DataFrame, seed: int = SEED) -> DataFrame:
    """One row per copy of ``mix``: ``block, spot, doc_id, source``; sorting by block and spot gives the order of training."""
    copies = plan.select("doc_id", "source", F.posexplode("blocks").alias("copy", "block"))
    return copies.select("block", F.xxhash64("block", "doc_id", "source", "copy", F.lit(seed)).alias("spot"), "doc_id", "source")


def stage(docs: DataFrame, max_epochs: float = 1.25) -> DataFrame:
    """The documents as often as the mix uses them, in their own columns; none is lost.

    All documents of a slice have the same number of copies, but in the slice where a source's broken pass ends.
    So texts stay where they are, and only those of such slices are joined with their places.
    """
    sized = settle(docs.select("doc_id", "source", count_tokens(F.col("text")).alias("n_tokens")).where("doc_id is not null"), "sized")
    bases, n_slices = plan_slices(sized, max_epochs, None)
    part, times, turn, doc = (unused(docs, n) for n in ("mix_slice", "mix_copies", "mix_turn", "mix_doc"))
    names = {c: unused(docs, f"mix{c}") for c in bases.columns}
    known = bases.select(*(F.col(c).alias(n) for c, n in names.items()))
    one = F.lit(1).cast("long")
    col = lambda c: F.col(names[c])
    cut = (col("epochs") - F.floor(col("epochs"))) * col("tokens")
    after = col("_before") + col("_in")
    worded = F.col("text").rlike(WORD_CHAR)
    copies = F.when(~F.coalesce(worded, F.lit(False)) | F.col("doc_id").isNull() | col("epochs").isNull(), one).when(after <= cut, F.floor(col("epochs")) + 1).when(col("_before") >= cut, F.floor(col("epochs")))
    if bases.count() <= BROADCAST_ROWS:
        known = F.broadcast(known)
    told = docs.withColumn(part, _slice(n_slices)).join(known, F.col("source").eqNullSafe(col("_source")) & (F.col(part) == col("_part")), "left").withColumn(times, copies.cast("long"))
    own = [F.col(f"`{c}`") for c in docs.columns]
    plan = settle(plan_mix(sized, max_epochs, only_cut=(bases, n_slices)).groupBy(F.col("doc_id").alias(doc), F.col("source").alias(names["_source"])).agg(F.max("copies").alias(turn)), "cut")
    broken = told.where(F.col(times).isNull()).select(*own).join(plan, (F.col("doc_id") == F.col(doc)) & F.col("source").eqNullSafe(col("_source")), "left").select(*own, F.coalesce(turn, one).alias(times))
    both = told.where(F.col(times).isNotNull()).select(*own, times).unionByName(broken)
    return both.select(*own, F.explode(F.sequence(one, F.col(times))).alias(turn)).drop(turn)
