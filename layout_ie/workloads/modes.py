"""The four tasks under each access path; the answers do not depend on it.

Regions and indices are written once per state of the source tables, as an offline step would; rules then
read only them.  ``none`` scans the plain relation.  ``text`` takes matches and their boxes from the postings.
``region`` reads the clustered relation: bucketed by page, so that rules meet without an exchange, and sorted by
position within a bucket, so that a constant box reads few row groups.  ``text+region`` has both, and ``auto``
chooses by what the indices know of the rule's phrases and boxes.
"""

from __future__ import annotations

import hashlib
import tempfile

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..baselines.other_ways import left_bar_per_page, names_per_page, nest, right_of_match_per_page, top_term_per_page, udf_dictionary, udf_phrase
from ..functions.predicates import ascii_word, strict_east_of, strict_south_of, within
from ..index import region as region_index
from ..index import text as text_index
from ..model import Box
from ..sources import sheets
from . import tasks

HEAD, WORD, TERM = "Return Flag", "Returned", "Order Summary"
NAMES = ("Returned", "Accepted")
#: The phrases of each task, and the constant box in which it looks.
PHRASES = {"q1": {}, "q2": {"t": TERM}, "q3": {"h": HEAD, **{w: w for w in NAMES}}, "q4": {"h": HEAD, "m": WORD}}
BOXES = {"q1": tasks.LEFT_BAR, "q2": tasks.TOP_SHEETS, "q3": None, "q4": None}


def _files(spark: SparkSession, path: str):  # noqa: ANN202
    hadoop = spark._jvm.org.apache.hadoop.fs.Path(path)
    store = hadoop.getFileSystem(spark._jsparkSession.sessionState().newHadoopConf())
    return store, hadoop


def index_folder(spark: SparkSession, sf_dir: str) -> str:
    """A folder for this state of the source tables, below the one that the cluster shares.

    A local temporary one is taken only where no shared one is set.
    """
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.sparkContext.getCheckpointDir() or f"file://{tempfile.gettempdir()}/layout-index"
    state = [sf_dir]
    for name in ("lineitem", "orders", "part"):
        store, path = _files(spark, f"{sf_dir}/{name}.parquet")
        status = store.getFileStatus(path)
        state += [str(status.getModificationTime()), str(store.getContentSummary(path).getLength())]
    return f"{base.rstrip('/')}/index-{spark.sparkContext.applicationId}-{hashlib.sha1(' '.join(state).encode()).hexdigest()[:12]}"


def _exists(spark: SparkSession, path: str) -> bool:
    store, marker = _files(spark, f"{path}/_SUCCESS")
    return store.exists(marker)


def stored_regions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The drawn boxes as a plain table."""
    path = f"{index_folder(spark, sf_dir)}/regions"
    if not _exists(spark, path):
        sheets.boxes(spark, sf_dir).write.mode("overwrite").parquet(path)
    return spark.read.schema(sheets.SCHEMA).parquet(path)


def stored_postings(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = f"{index_folder(spark, sf_dir)}/postings"
    if not _exists(spark, path):
        return text_index.write_text_index(stored_regions(spark, sf_dir), path)
    return spark.read.schema("term string, next string, page_id long, region_id string, pos long, x_l long, y_l long, x_h long, y_h long").parquet(path)


def stored_clustered(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The relation bucketed by page and sorted by position in each bucket."""
    folder = index_folder(spark, sf_dir)
    table = f"clustered_{folder.rsplit('-', 1)[1]}"
    if not (_exists(spark, f"{folder}/clustered") and spark.catalog.tableExists(table)):
        return region_index.build_region_index(stored_regions(spark, sf_dir), table, f"{folder}/clustered")
    return spark.table(table)


def stored_summary(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Counts of regions per grid cell: what the choice of a path knows of a box."""
    path = f"{index_folder(spark, sf_dir)}/summary"
    if not _exists(spark, path):
        region_index.summarise(stored_clustered(spark, sf_dir)).coalesce(1).write.mode("overwrite").parquet(path)
    return spark.read.schema("x_cell int, y_cell int, n long").parquet(path)


def choose(spark: SparkSession, sf_dir: str, task: str) -> str:
    """The access path for a task, from posting counts and the share of regions in its box.

    All tasks but the second put regions of a page together, which the clustered relation does without an exchange.
    """
    phrases, box = PHRASES[task], BOXES[task]
    inside, regions = region_index.box_count(stored_summary(spark, sf_dir), box)
    rarest = min(text_index.posting_counts(stored_postings(spark, sf_dir), phrases).values()) if phrases else None
    return region_index.choose_access(rarest, inside / max(1, regions) if box else None, regions, by_page=task != "q2")


def _space(spark: SparkSession, sf_dir: str, mode: str) -> DataFrame:
    return stored_clustered(spark, sf_dir) if "region" in mode else stored_regions(spark, sf_dir)


def _phrase(spark: SparkSession, sf_dir: str, mode: str, phrase: str) -> DataFrame:
    """The nodes that hold a phrase: from the postings, which cover their boxes, by a UDF, or by a scan."""
    if "text" in mode:
        return text_index.lookup_phrase(stored_postings(spark, sf_dir), phrase, distinct=False)
    test: Column = udf_phrase(phrase)("text") if mode == "udf" else F.col("text").rlike(ascii_word(phrase))
    return _space(spark, sf_dir, mode).where(F.col("text").isNotNull() & test)


def _nested(spark: SparkSession, sf_dir: str) -> DataFrame:
    return nest(stored_regions(spark, sf_dir))


def right_of_match(spark: SparkSession, sf_dir: str, mode: str = "none") -> DataFrame:
    """Distinct answers of the fourth task with the access path ``mode``.

    The pair of matches comes first; the unfiltered regions then meet only its pages.
    """
    mode = choose(spark, sf_dir, "q4") if mode == "auto" else mode
    if mode == "per_page":
        return right_of_match_per_page(_nested(spark, sf_dir), ascii_word(HEAD), ascii_word(WORD))
    h, m = (tasks._edges(_phrase(spark, sf_dir, mode, p), a) for p, a in ((HEAD, "h"), (WORD, "m")))
    pairs = m.join(h, (F.col("m.page_id") == F.col("h.page_id")) & strict_south_of(Box.of("m"), Box.of("h")), "left_semi").select("m.*").alias("m")
    s = tasks._edges(_space(spark, sf_dir, mode), "s")
    return s.join(pairs, (F.col("s.page_id") == F.col("m.page_id")) & strict_east_of(Box.of("s"), Box.of("m")), "left_semi").select("s.page_id", "s.region_id")


def left_bar(spark: SparkSession, sf_dir: str, mode: str = "none") -> DataFrame:
    """The first task, which has no text condition.

    Only the bound on the shared edge may prune the index: the others hold for whole groups.
    """
    mode = choose(spark, sf_dir, "q1") if mode == "auto" else mode
    if mode == "per_page":
        return left_bar_per_page(_nested(spark, sf_dir), 3, tasks.LEFT_BAR)
    return tasks.left_bar(_space(spark, sf_dir, mode))


def top_term(spark: SparkSession, sf_dir: str, mode: str = "none") -> DataFrame:
    """The second task: a phrase in a constant box.  The text index covers boxes, so it answers alone."""
    mode = choose(spark, sf_dir, "q2") if mode == "auto" else mode
    if mode == "per_page":
        return top_term_per_page(_nested(spark, sf_dir), ascii_word(TERM), tasks.TOP_SHEETS)
    hit = _phrase(spark, sf_dir, mode, TERM).where(within(Box.of(), tasks.TOP_SHEETS)).select("page_id", "region_id")
    return hit.distinct() if "text" in mode else hit


def names(spark: SparkSession, sf_dir: str, mode: str = "none") -> DataFrame:
    """The third task: dictionary words south or east of a heading; postings alone answer it."""
    mode = choose(spark, sf_dir, "q3") if mode == "auto" else mode
    if mode == "per_page":
        return names_per_page(_nested(spark, sf_dir), ascii_word(HEAD), [ascii_word(w) for w in NAMES])
    if "text" in mode:
        found = text_index.lookup_terms(stored_postings(spark, sf_dir), list(NAMES)).drop("term").distinct()
    elif mode == "udf":
        found = stored_regions(spark, sf_dir).where(udf_dictionary(NAMES)("text"))
    else:
        hit = F.lit(False)
        for w in NAMES:
            hit = hit | F.col("text").rlike(ascii_word(w))
        found = _space(spark, sf_dir, mode).where(F.col("text").isNotNull() & hit)
    v, h = tasks._edges(found, "v"), tasks._edges(_phrase(spark, sf_dir, mode, HEAD), "h")
    place = strict_south_of(Box.of("v"), Box.of("h")) | strict_east_of(Box.of("v"), Box.of("h"))
    return v.join(h, (F.col("v.page_id") == F.col("h.page_id")) & place, "left_semi").select("v.page_id", "v.region_id")


#: Each task by name, with the access paths it has.
TASKS = {
    "q1": (left_bar, ("none", "region", "auto", "per_page")),
    "q2": (top_term, ("none", "text", "region", "text+region", "auto", "udf", "per_page")),
    "q3": (names, ("none", "text", "region", "text+region", "auto", "udf", "per_page")),
    "q4": (right_of_match, ("none", "text", "region", "text+region", "auto", "udf", "per_page")),
}
