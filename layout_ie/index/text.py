"""Inverted text index: one row per word occurrence, written by term bucket and sorted by term.

A hot term is spread over ``salts`` files, so that no bucket holds it alone; a
lookup reads all salts of its terms.
"""

from __future__ import annotations

import re

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.spans import TOKEN, ascii_lower

SALTS = 8


BOX = ("x_l", "y_l", "x_h", "y_h")


def _words(text: str = "text"):  # noqa: ANN202
    return F.regexp_extract_all(ascii_lower(F.col(text)), F.lit(TOKEN), F.lit(0))


def build_text_index(regions: DataFrame) -> DataFrame:
    """POSTINGS: term, page_id, region_id, pos (0-based place in the node's text)."""
    return regions.where("text is not null").select("page_id", "region_id", F.posexplode(_words()).alias("pos", "term")).select("term", "page_id", "region_id", F.col("pos").cast("long").alias("pos"))


def build_covering_index(regions: DataFrame) -> DataFrame:
    """Postings that also hold the word after (null if no single blank leads to one) and the node's box.

    A phrase of two words is then one filter, and a rule gets the boxes of its matches
    without reading the regions.  As the next word counts after one blank only, the index finds a phrase where a
    scan for it does, and nowhere else.
    """
    held = regions.where("text is not null").select("page_id", "region_id", *BOX, _words().alias("_w"), F.split("text", TOKEN, -1).alias("_gap"))
    rows = held.select("page_id", "region_id", *BOX, "_w", "_gap", F.posexplode("_w").alias("pos", "term"))
    after = F.when(F.get(F.col("_gap"), F.col("pos") + 1) == " ", F.get(F.col("_w"), F.col("pos") + 1))
    return rows.select("term", after.alias("next"), "page_id", "region_id", F.col("pos").cast("long").alias("pos"), *BOX)


#: Rows of postings in one written file, about.
FILE_ROWS = 4_000_000


def write_text_index(regions: DataFrame, path: str, buckets: int | None = None) -> DataFrame:
    """Store the covering postings sorted by term, so that a lookup skips files and row groups by their bounds.

    A hot term is spread over ``SALTS`` ranges of pages.  Files follow the number of regions (a few words each).
    """
    spark = regions.sparkSession
    found = build_covering_index(regions).withColumn("salt", F.pmod(F.xxhash64("page_id"), F.lit(SALTS)))
    buckets = buckets or max(spark.sparkContext.defaultParallelism, 3 * regions.count() // FILE_ROWS)
    found.repartitionByRange(buckets, "term", "next", "salt").sortWithinPartitions("term", "next", "salt", "page_id", "region_id", "pos").drop("salt").write.mode("overwrite").parquet(path)
    return spark.read.schema(found.drop("salt").schema).parquet(path)


def lookup_terms(postings: DataFrame, terms: list[str]) -> DataFrame:
    """Nodes with one of the words, with their boxes if the index covers them."""
    held = [c for c in BOX if c in postings.columns]
    return postings.where(F.col("term").isin([t.lower() for t in terms])).select("term", "page_id", "region_id", *held).distinct()


def phrase_words(phrase: str) -> list[str]:
    """The words of a literal phrase in lower case; other phrases are for a scan and raise."""
    if not re.fullmatch(f"{TOKEN}(?: {TOKEN})*", phrase):
        raise ValueError(f"the text index holds words after single blanks, not {phrase!r}")
    return phrase.lower().split(" ")


def lookup_phrase(postings: DataFrame, phrase: str, distinct: bool = True) -> DataFrame:
    """Nodes where the words of a literal phrase follow each other after one blank, with their boxes.

    ``postings`` cover the next word.  One filter for the first two words, one join on node
    and place for each further one.  Without ``distinct`` a node comes once an occurrence, which semi-joins
    do not mind.
    """
    words = phrase_words(phrase)
    pair = lambda i: (F.col("term") == words[i]) & (F.col("next") == words[i + 1] if i + 1 < len(words) else F.lit(True))
    held = [c for c in BOX if c in postings.columns]
    found = postings.where(pair(0)).select("page_id", "region_id", "pos", *held)
    for i in range(1, len(words) - 1):
        nxt = postings.where(pair(i)).select("page_id", "region_id", (F.col("pos") - i).alias("pos"))
        found = found.join(nxt, ["page_id", "region_id", "pos"])
    nodes = found.select("page_id", "region_id", *held)
    return nodes.distinct() if distinct else nodes


def phrase_sql(phrase: str, postings: str, regions: str | None) -> str:
    """The regions of ``lookup_phrase`` as a subquery; without ``regions`` ids and boxes as the postings cover them."""
    words = phrase_words(phrase)
    pair = lambda i: f"p{i}.term = '{words[i]}'" + (f" AND p{i}.next = '{words[i + 1]}'" if i + 1 < len(words) else "")
    joins = " ".join(f"JOIN {postings} p{i} ON p{i}.page_id = p0.page_id AND p{i}.region_id = p0.region_id AND p{i}.pos = p0.pos + {i} AND {pair(i)}" for i in range(1, len(words) - 1))
    held = ", ".join(f"p0.{c}" for c in ("page_id", "region_id", *BOX))
    if regions is None:
        return f"(SELECT DISTINCT {held} FROM {postings} p0 {joins} WHERE {pair(0)})"
    hits = f"SELECT p0.page_id, p0.region_id FROM {postings} p0 {joins} WHERE {pair(0)}"
    return f"(SELECT r.* FROM {regions} r LEFT SEMI JOIN ({hits}) h ON r.page_id = h.page_id AND r.region_id = h.region_id)"


def posting_counts(postings: DataFrame, terms: dict[str, str]) -> dict[str, int]:
    """Occurrences of the rarest word of each alias's phrase, for the order of joins."""
    words = {a: re.findall(TOKEN, p.lower()) for a, p in terms.items()}
    flat = sorted({w for ws in words.values() for w in ws})
    found = {r["term"]: r["n"] for r in postings.where(F.col("term").isin(flat)).groupBy("term").agg(F.count("*").alias("n")).collect()}
    return {a: min((found.get(w, 0) for w in ws), default=0) for a, ws in words.items()}
