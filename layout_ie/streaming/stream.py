"""Growing collections: rules page by page on a stream, recrawls, extraction rates, changes between crawls."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..baselines.other_ways import right_of_match_per_page
from ..sources.pages import render_pages

PAGE_SCHEMA = "page_id long, url string, html string"


def page_stream(spark: SparkSession, path: str, schema: str = PAGE_SCHEMA, files_per_batch: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).parquet(path)


def stream_rules(nested: DataFrame, heading_pattern: str, match_pattern: str) -> DataFrame:
    """A rule over a stream of nested pages: stateless, append mode, no shuffle."""
    return right_of_match_per_page(nested, heading_pattern, match_pattern)


def stream_regions(pages: DataFrame) -> DataFrame:
    """Regions of arriving pages."""
    return render_pages(pages)


def drop_recrawls(pages: DataFrame, time: str = "crawled", delay: str = "1 day") -> DataFrame:
    """One page per url within the watermark; later ones past it are dropped."""
    return pages.withWatermark(time, delay).dropDuplicatesWithinWatermark(["url"])


def run_available(df: DataFrame, sink: Callable[[DataFrame, int], None], checkpoint: str) -> None:
    """Run a stream over what is there now."""
    df.writeStream.foreachBatch(sink).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()


def upsert_sink(path: str, keys: list[str]) -> Callable[[DataFrame, int], None]:
    """Write each batch to a folder of its own number, so that a batch that runs again replaces itself."""

    def write(batch: DataFrame, number: int) -> None:
        batch.dropDuplicates(keys).write.mode("overwrite").parquet(f"{path}/batch={number}")

    return write


# ---------------------------------------------------------------- extraction rates
def tumbling(events: DataFrame, width: str = "1 hour") -> DataFrame:
    return events.groupBy(F.window("ts", width).alias("w"), "event_type").agg(F.count("*").alias("n"), F.sum("value").alias("total"))


def sliding(events: DataFrame, width: str = "2 hours", step: str = "1 hour") -> DataFrame:
    return events.groupBy(F.window("ts", width, step).alias("w"), "event_type").agg(F.count("*").alias("n"))


def sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    return events.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n"))


# ---------------------------------------------------------------- change between crawls
def changed_matches(matches: DataFrame) -> DataFrame:
    """Per url: what a crawl found that the one before did not, and the other way round.

    ``matches`` is a stream of ``url, crawl, found`` with the matches of one crawl as a joined string.
    """

    def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        known = set(state.get[0].split("\n")) - {""} if state.exists else set()
        rows = []
        for crawl, found in sorted((r.crawl, r.found) for f in frames for r in f.itertuples()):
            now = set((found or "").split("\n")) - {""}
            rows.append((key[0], int(crawl), len(now - known), len(known - now)))
            known = now
        state.update(("\n".join(sorted(known)),))
        yield pd.DataFrame(rows, columns=["url", "crawl", "n_new", "n_gone"])

    return matches.groupBy("url").applyInPandasWithState(step, "url string, crawl long, n_new long, n_gone long", "known string", "append", GroupStateTimeout.NoTimeout)
