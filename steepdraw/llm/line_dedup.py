"""Site-relative line removal, in DataFrame functions only.

Rows are grouped by host.  For each line, the pages of the host that contain it (once per page)
are divided by all pages of the host; lines whose ratio exceeds `ratio`, on at least `min_pages`
pages, are boilerplate and go from every page of that host.  Copies of a page count once, so a
page crawled a thousand times doesn't turn its own text into boilerplate.

At most (mean lines per page) / `ratio` lines of a host can exceed the ratio, so a host's list is
short whatever its size.  Lists travel to the pages, pages don't travel to the lists: a hot host
is aggregated map side, and the lists are broadcast if their measured size allows; otherwise the
engine splits the pages of a hot host.

Lines are compared by 64-bit hash without surrounding spaces; blank lines are kept.  Null text stays null;
a null host is a group of its own; repeated rows are copies of one page; an empty text has one
blank line.  Empty tables give empty results.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import BROADCAST_BYTES, materialise

RATIO = 0.05
MIN_PAGES = 5


def _line_hash(line: Column) -> Column:
    return F.xxhash64(F.trim(line))


def boilerplate(pages: DataFrame, host: str = "source", ratio: float = RATIO, min_pages: int = MIN_PAGES) -> DataFrame:
    """host and lines (hashes of the host's boilerplate lines)."""
    lines = F.array_distinct(F.transform(F.filter(F.split("text", "\n"), lambda x: F.trim(x) != ""), _line_hash))
    # copies of one page are one page: the page is named by its host and content
    own = pages.where("text is not null").select(F.col(host).alias("host"), F.xxhash64("text", F.lit(1)).alias("page"), lines.alias("lines"))
    one = own.groupBy("host", "page").agg(F.first("lines").alias("lines"))
    totals = one.groupBy("host").agg(F.count(F.lit(1)).alias("pages"))
    counts = one.select("host", F.explode("lines").alias("line")).groupBy("host", "line").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") >= min_pages)
    over = counts.join(totals.withColumnRenamed("host", "host_"), F.col("host").eqNullSafe(F.col("host_"))).where(F.col("n") > F.lit(ratio) * F.col("pages"))
    return over.groupBy("host").agg(F.collect_list("line").alias("lines"))


def remove_boilerplate(pages: DataFrame, host: str = "source", ratio: float = RATIO, min_pages: int = MIN_PAGES) -> DataFrame:
    """The pages with boilerplate lines removed from text, and _n_lines, _n_removed.

    Columns of these two names in the input are replaced; all others come back as they are.
    """
    lists = materialise(boilerplate(pages, host, ratio, min_pages), "boilerplate")
    size = lists.agg(F.sum(F.size("lines") + 8).alias("longs")).first()["longs"] or 0
    lists = F.broadcast(lists) if 8 * size <= BROADCAST_BYTES else lists
    whole = F.struct(*[F.col(f"`{c}`") for c in pages.columns])
    joined = pages.select(whole.alias("row"), F.col(f"`{host}`").alias("own")).join(lists, F.col("own").eqNullSafe(F.col("host")), "left")
    text = F.col("row.text")
    split = F.split(text, "\n")
    drop = lambda x: F.array_contains(F.col("lines"), _line_hash(x)) & (F.trim(x) != "")
    whole_stays = F.col("lines").isNull() | text.isNull()
    kept = F.when(whole_stays, text).otherwise(F.array_join(F.filter(split, lambda x: ~drop(x)), "\n"))
    gone = F.when(whole_stays, F.lit(0)).otherwise(F.size(F.filter(split, drop)))
    n = F.when(text.isNull(), F.lit(0)).otherwise(F.size(split))
    done = joined.select("row", kept.alias("kept"), n.cast("long").alias("n"), gone.cast("long").alias("gone"))
    names = [c for c in pages.columns if c not in ("_n_lines", "_n_removed")]
    return done.select(*[F.col("kept").alias(c) if c == "text" else F.col(f"row.`{c}`") for c in names], F.col("n").alias("_n_lines"), F.col("gone").alias("_n_removed"))


#: Base SQL of the same rule, over a view `documents` (for DuckDB).
ORACLE_SQL = f"""
WITH pages AS (
  SELECT DISTINCT source, text FROM documents WHERE text IS NOT NULL
), totals AS (
  SELECT source, count(*) AS pages FROM pages GROUP BY source
), lines AS (
  SELECT source, unnest(list_distinct(list_transform(string_split(text, chr(10)), lambda x: trim(x)))) AS line FROM pages
), over_ AS (
  SELECT l.source, l.line FROM lines l JOIN totals t ON l.source IS NOT DISTINCT FROM t.source
  WHERE l.line <> '' GROUP BY l.source, l.line, t.pages
  HAVING count(*) >= {MIN_PAGES} AND count(*) > {RATIO} * t.pages
), lists AS (
  SELECT source, list(line) AS gone FROM over_ GROUP BY source
), parts AS (
  SELECT d.doc_id, string_split(d.text, chr(10)) AS own, coalesce(l.gone, []) AS gone
  FROM documents d LEFT JOIN lists l ON d.source IS NOT DISTINCT FROM l.source
)
SELECT doc_id, len(own)::BIGINT AS n_lines,
       len(list_filter(own, lambda x: list_contains(gone, trim(x))))::BIGINT AS n_removed,
       sha256(array_to_string(list_filter(own, lambda x: NOT list_contains(gone, trim(x))), chr(10))) AS kept_sha256
FROM parts
"""
