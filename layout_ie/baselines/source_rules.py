"""Rules on the page source alone: tags and paths, no geometry.

``identical`` covers every markup that can align cells, ``approximate`` only one of them,
``alternate`` replaces a position that source cannot express by a place in document order.
``PARTS`` lists what each rule is made of, to compare its size with that of a visual rule.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.predicates import ascii_word
from ..operators.visual import phrase_regions


def _ordinals(df: DataFrame) -> DataFrame:
    """Ordinals of a cell below the grid: ``i`` of its row (or list), ``j`` in it."""
    path = F.split("region_id", r"\.")
    return df.where(F.col("region_id").startswith("1.3.")).withColumns({"_i": F.get(path, F.lit(2)).cast("long"), "_j": F.get(path, F.lit(3)).cast("long")})


def _named(vis: DataFrame, words: list[str]) -> DataFrame:
    hit = F.lit(False)
    for w in words:
        hit = hit | F.col("text").rlike(ascii_word(w))
    return vis.where(hit)


def names_in_table(vis: DataFrame, heading: str, words: list[str], tags: tuple[str, ...]) -> DataFrame:
    """Cells of the heading's row or column after it, by sibling ordinals, for the cell tags given."""
    h = _ordinals(phrase_regions(vis, heading)).select("page_id", F.col("_i").alias("h_i"), F.col("_j").alias("h_j"))
    v = _ordinals(_named(vis, words).where(F.col("html_tag").isin(*tags)))
    after = ((F.col("_j") == F.col("h_j")) & (F.col("_i") > F.col("h_i"))) | ((F.col("_i") == F.col("h_i")) & (F.col("_j") > F.col("h_j")))
    return v.join(h, "page_id").where(after).select("page_id", "region_id").distinct()


def identical(vis: DataFrame, heading: str = "Return Flag", words: tuple[str, ...] = ("Returned", "Accepted")) -> DataFrame:
    return names_in_table(vis, heading, list(words), ("td", "div", "li"))


def approximate(vis: DataFrame, heading: str = "Return Flag", words: tuple[str, ...] = ("Returned", "Accepted")) -> DataFrame:
    return names_in_table(vis, heading, list(words), ("td",))


def alternate(vis: DataFrame, word: str = "Returned", follow: int = 3) -> DataFrame:
    """The next ``follow`` texts of the document after a cell with the word."""
    w = Window.partitionBy("page_id").orderBy("ord")
    cell = F.col("html_tag").isin("td", "div", "li") & F.col("region_id").startswith("1.3.") & F.col("text").rlike(ascii_word(word))
    marked = vis.withColumn("_last", F.max(F.when(cell, F.col("ord"))).over(w.rowsBetween(Window.unboundedPreceding, -1)))
    return marked.where(F.col("ord") - F.col("_last") <= follow).select("page_id", "region_id")


# ---------------------------------------------------------------- the other tasks
CELL_TAGS = ("td", "div", "li")


def _stacks(vis: DataFrame, tags: tuple[str, ...]) -> DataFrame:
    """Nodes with the stack that their markup puts them in: the list of an item, or the column of a cell."""
    path = F.split("region_id", r"\.")
    listed = F.array_join(F.slice(path, F.lit(1), F.size(path) - 1), ".")
    column = F.concat(F.lit("column "), F.get(path, F.lit(3)))
    stack = F.when(F.col("html_tag") == "li", listed).when(F.col("html_tag").isin("td", "div") & F.col("region_id").startswith("1.3."), column)
    return vis.where(F.col("html_tag").isin(*tags)).withColumn("_stack", stack).where("_stack is not null")


def bar_identical(vis: DataFrame, n: int = 3, tags: tuple[str, ...] = CELL_TAGS) -> DataFrame:
    """Members of stacks of more than ``n`` nodes, for every markup that stacks nodes; where they stand is not said."""
    size = F.count("*").over(Window.partitionBy("page_id", "_stack"))
    return _stacks(vis, tags).withColumn("_n", size).where(F.col("_n") > n).select("page_id", "region_id")


def bar_approximate(vis: DataFrame, n: int = 3) -> DataFrame:
    """Lists alone."""
    return bar_identical(vis, n, ("li",))


def bar_alternate(vis: DataFrame, n: int = 3) -> DataFrame:
    """The page's first list stands in for the place at the left."""
    lists = _stacks(vis, ("li",)).withColumn("_first", F.min_by("_stack", "ord").over(Window.partitionBy("page_id")))
    size = F.count("*").over(Window.partitionBy("page_id"))
    return lists.where("_stack = _first").withColumn("_n", size).where(F.col("_n") > n).select("page_id", "region_id")


def class_identical(vis: DataFrame, term: str = "Order Summary", tags: tuple[str, ...] = ("h1", "h2", "h3")) -> DataFrame:
    """Headings of every level that hold the term."""
    return phrase_regions(vis.where(F.col("html_tag").isin(*tags)), term).select("page_id", "region_id")


def class_approximate(vis: DataFrame, term: str = "Order Summary") -> DataFrame:
    """Top headings that say the term and nothing else."""
    return vis.where((F.col("html_tag") == "h1") & (F.col("text") == term)).select("page_id", "region_id")


def class_alternate(vis: DataFrame, term: str = "Order Summary", first: int = 6) -> DataFrame:
    """The term among the first texts of the document, instead of at the top of the page."""
    return phrase_regions(vis.where(F.col("ord") <= first), term).select("page_id", "region_id")


def _placed(vis: DataFrame) -> DataFrame:
    """Grid nodes with their row and column as the markup has them: lists go by columns, all others by rows."""
    lists = F.col("template") == 2
    return _ordinals(vis).withColumns({"_row": F.when(lists, F.col("_j")).otherwise(F.col("_i")), "_col": F.when(lists, F.col("_i")).otherwise(F.col("_j"))})


def right_identical(vis: DataFrame, heading: str = "Return Flag", word: str = "Returned", tags: tuple[str, ...] = CELL_TAGS) -> DataFrame:
    """Cells after a cell with the word in its row, where that cell is below the heading in its column."""
    h = _placed(phrase_regions(vis, heading)).select("page_id", F.col("_row").alias("h_row"), F.col("_col").alias("h_col"))
    cells = _placed(vis.where(F.col("html_tag").isin(*tags)))
    m = phrase_regions(cells, word).join(h, "page_id").where((F.col("_col") == F.col("h_col")) & (F.col("_row") > F.col("h_row")))
    m = m.select("page_id", F.col("_row").alias("m_row"), F.col("_col").alias("m_col")).distinct()
    on = (F.col("_row") == F.col("m_row")) & (F.col("_col") > F.col("m_col"))
    return cells.join(m, "page_id").where(on).select("page_id", "region_id").distinct()


def right_approximate(vis: DataFrame) -> DataFrame:
    return right_identical(vis, tags=("td",))


#: What a source rule says: node sets it draws from, conditions, constants, groupings.
PARTS = {
    "q1_identical": (("li", "td", "div"), ("same list", "same column of td", "same column of div", "count"), ("li", "td", "div", "3"), ("stack",)),
    "q1_approximate": (("li",), ("same list", "count"), ("li", "3"), ("stack",)),
    "q1_alternate": (("li",), ("same list", "first list", "count"), ("li", "3"), ("stack",)),
    "q2_identical": (("h1", "h2", "h3"), ("holds term",), ("h1", "h2", "h3", "term"), ()),
    "q2_approximate": (("h1",), ("is term",), ("h1", "term"), ()),
    "q2_alternate": (("text",), ("holds term", "among first"), ("term", "6"), ()),
    "q3_identical": (("td", "div", "li", "heading"), ("word", "grid", "same row", "later in row", "same column", "later in column"), ("td", "div", "li", "heading", "words"), ()),
    "q3_approximate": (("td", "heading"), ("word", "grid", "same row", "later in row", "same column", "later in column"), ("td", "heading", "words"), ()),
    "q4_identical": (("td", "div", "li", "heading", "match"), ("word", "grid", "same column", "later in column", "rows of lists", "same row", "later in row"), ("td", "div", "li", "heading", "word"), ()),
    "q4_approximate": (("td", "heading", "match"), ("word", "grid", "same column", "later in column", "same row", "later in row"), ("td", "heading", "word"), ()),
    "q4_alternate": (("td", "div", "li"), ("word", "grid", "among next"), ("td", "div", "li", "word", "3"), ()),
}


def proximity(vis: DataFrame, heading: str = "Return Flag", d: int = 20) -> DataFrame:
    """Per markup: headings whose next text in the source within ``d`` characters is, or is not, the box right below.

    Source closeness is not closeness on the page.
    """
    w = Window.partitionBy("page_id").orderBy("ord")
    nxt = vis.withColumns({"_n": F.lead("region_id").over(w), "_gap": F.lead("text_start").over(w) - F.col("text_end")})
    h = phrase_regions(nxt, heading).where(F.col("_gap") <= d)
    below = vis.select("page_id", F.col("region_id").alias("b_id"), F.col("x_l").alias("b_x_l"), F.col("x_h").alias("b_x_h"), F.col("y_l").alias("b_y_l"))
    pairs = h.join(below, "page_id").where((F.col("b_y_l") >= F.col("y_h")) & (F.col("b_x_l") < F.col("x_h")) & (F.col("x_l") < F.col("b_x_h")))
    first = pairs.groupBy("page_id", "template", "region_id", "_n").agg(F.min_by("b_id", F.struct(F.col("b_y_l") - F.col("y_h"), F.col("b_id"))).alias("_south"))
    return first.groupBy("template").agg(F.count("*").alias("n_headings"), F.count(F.when(F.col("_n") == F.col("_south"), 1)).alias("n_agree"))
