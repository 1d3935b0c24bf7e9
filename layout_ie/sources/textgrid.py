"""Text grid: documents as monospace drawings; lines are parents, words their children."""

from __future__ import annotations

import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.spans import match_offsets
from ..session import ship
from .tables import load

CELL_W, CELL_H = 8, 20
#: What parts words on a line, in all engines alike.
WORD = r"[^ \t\r\f]+"


def numbered_lines(docs: DataFrame) -> DataFrame:
    """``page_id, l, line, at``: each line with its number (from 0) and its offset in the text."""
    starts = F.concat(F.array(F.lit(0).cast("long")), F.transform(match_offsets(F.col("text"), "\n"), lambda m: m["end"]))
    lines = F.arrays_zip(F.split("text", "\n", -1).alias("line"), starts.alias("at"))
    return docs.select(F.col("doc_id").alias("page_id"), F.posexplode(lines).alias("l", "x")).select("page_id", "l", "x.line", "x.at")


def words(docs: DataFrame) -> DataFrame:
    """One row per word: box, span in the document, and path ``1.line.word``; one pass over each text."""
    ship(docs.sparkSession)
    names = ("l", "w", "at", "c", "n", "text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rx = re.compile(WORD)
        for batch in batches:
            rows: list[tuple] = []
            doc: list[int] = []
            for i, text in enumerate(batch.column(1).to_pylist()):
                at, before = 0, len(rows)
                for l, line in enumerate((text or "").split("\n")):
                    rows += [(l, w, at, m.start(), m.end() - m.start(), m.group()) for w, m in enumerate(rx.finditer(line))]
                    at += len(line) + 1
                doc += [i] * (len(rows) - before)
            if rows:
                columns = [pa.array(c, pa.string() if k == "text" else pa.int64()) for k, c in zip(names, zip(*rows, strict=True), strict=True)]
                yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(doc, pa.int64())), *columns], ["page_id", *names])

    found = docs.select(F.col("doc_id").cast("long").alias("page_id"), "text").mapInArrow(run, "page_id long, l long, w long, at long, c long, n long, text string")
    c, n = F.col("c"), F.col("n")
    return found.select(
        "page_id", F.concat(F.lit("1."), (F.col("l") + 1).cast("string"), F.lit("."), (F.col("w") + 1).cast("string")).alias("region_id"),
        (c * CELL_W).alias("x_l"), (F.col("l") * CELL_H).alias("y_l"), ((c + n) * CELL_W).alias("x_h"), ((F.col("l") + 1) * CELL_H).alias("y_h"),
        (F.col("at") + c).alias("text_start"), (F.col("at") + c + n).alias("text_end"), "text",
    )


def regions(spark: SparkSession, sf_dir: str) -> DataFrame:
    return words(load(spark, sf_dir, "documents").select("doc_id", "text"))


def line_regions(docs: DataFrame) -> DataFrame:
    """The parent boxes: one per line, and the page."""
    at = F.col("at")
    one = numbered_lines(docs).select(
        "page_id", F.concat(F.lit("1."), (F.col("l") + 1).cast("string")).alias("region_id"), F.lit(0).cast("long").alias("x_l"), (F.col("l") * CELL_H).cast("long").alias("y_l"),
        (F.length("line") * CELL_W).cast("long").alias("x_h"), ((F.col("l") + 1) * CELL_H).cast("long").alias("y_h"), at.alias("text_start"), (at + F.length("line")).alias("text_end"), F.lit(2).cast("long").alias("depth"),
    )
    top = one.groupBy("page_id").agg(
        F.lit("1").alias("region_id"), F.min("x_l").alias("x_l"), F.min("y_l").alias("y_l"), F.max("x_h").alias("x_h"), F.max("y_h").alias("y_h"),
        F.min("text_start").alias("text_start"), F.max("text_end").alias("text_end"), F.lit(1).cast("long").alias("depth"),
    )
    return one.unionByName(top)
