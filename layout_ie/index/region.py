"""Region index: the relation clustered by page and position, a page grid, and the choice of access path."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.predicates import within
from ..model import Box

#: Rows of the clustered relation in one bucket, about, and bytes of its row groups.
BUCKET_ROWS, ROW_GROUP = 2_000_000, 4 << 20
#: Grid of the summary: pixels of a cell, and cells a side at most (the last one is open).
CELL, CELLS = 50, 128


def build_region_index(regions: DataFrame, table: str, path: str, buckets: int | None = None) -> DataFrame:
    """Store the relation bucketed by page, so that pages meet without an exchange, and sorted by position in small row groups.

    The number of buckets follows that of the regions.
    """
    spark = regions.sparkSession
    buckets = buckets or max(spark.sparkContext.defaultParallelism, regions.count() // BUCKET_ROWS)
    spark.sql(f"DROP TABLE IF EXISTS {table}")
    writer = regions.repartition(buckets, "page_id").sortWithinPartitions("x_l", "y_l", "page_id").write.mode("overwrite")
    writer.option("path", path).option("parquet.block.size", ROW_GROUP).bucketBy(buckets, "page_id").sortBy("x_l", "y_l", "page_id").saveAsTable(table)
    return spark.table(table)


def lookup_box(index: DataFrame, box: Box) -> DataFrame:
    """Regions inside a constant box; the comparisons reach the scan."""
    return index.where(within(Box.of(), box))


def summarise(regions: DataFrame) -> DataFrame:
    """``x_cell, y_cell, n``: counts of regions by the cell of their upper left corner, of a bounded number of cells."""
    cell = lambda c: F.least(F.greatest(F.floor(F.col(c) / CELL), F.lit(0)), F.lit(CELLS - 1)).cast("int")
    return regions.groupBy(cell("x_l").alias("x_cell"), cell("y_l").alias("y_cell")).agg(F.count("*").alias("n"))


def box_count(summary: DataFrame, box: Box | None) -> tuple[int, int]:
    """About how many regions start inside the box, and how many there are."""
    inside = F.lit(True)
    for bound, low, cell in ((box and box.x_l, True, "x_cell"), (box and box.y_l, True, "y_cell"), (box and box.x_h, False, "x_cell"), (box and box.y_h, False, "y_cell")):
        if bound is not None:
            at = min(max(bound // CELL, 0), CELLS - 1)
            inside = inside & (F.col(cell) >= at if low else F.col(cell) <= at)
    row = summary.agg(F.sum(F.when(inside, F.col("n"))).alias("inside"), F.sum("n").alias("n")).first()
    return row["inside"] or 0, row["n"] or 0


def page_grid(regions: DataFrame, cell: int = 200) -> DataFrame:
    """One row per (region, cell it meets): an equi-join key for pairs on very large pages."""
    xs = F.sequence(F.floor(F.col("x_l") / cell), F.floor(F.col("x_h") / cell))
    ys = F.sequence(F.floor(F.col("y_l") / cell), F.floor(F.col("y_h") / cell))
    return regions.withColumn("cell_x", F.explode(xs)).withColumn("cell_y", F.explode(ys))


def grid_pairs(a: DataFrame, b: DataFrame, predicate, cell: int = 200) -> DataFrame:  # noqa: ANN001
    """Pairs of one page that meet: joined by cell, each pair kept in the lowest cell it shares."""
    left, right = page_grid(a, cell).alias("a"), page_grid(b, cell).alias("b")
    on = (F.col("a.page_id") == F.col("b.page_id")) & (F.col("a.cell_x") == F.col("b.cell_x")) & (F.col("a.cell_y") == F.col("b.cell_y"))
    lowest = (F.col("a.cell_x") == F.floor(F.greatest("a.x_l", "b.x_l") / cell)) & (F.col("a.cell_y") == F.floor(F.greatest("a.y_l", "b.y_l") / cell))
    return left.join(right, on).where(lowest & predicate(Box.of("a"), Box.of("b"))).select(F.col("a.page_id").alias("page_id"), F.col("a.region_id").alias("a_id"), F.col("b.region_id").alias("b_id"))


def choose_access(text_matches: int | None, box_share: float | None, regions: int, threshold: float = 0.25, by_page: bool = False) -> str:
    """Which index pays: the text index for phrases that are rare, the region index for boxes that hold little
    and for rules that put the regions of a page together."""
    text = text_matches is not None and text_matches <= threshold * max(1, regions)
    region = by_page or (box_share is not None and box_share <= threshold)
    return "text+region" if text and region else "text" if text else "region" if region else "none"
