"""Line dedup by site-relative frequency.

For each host, the pages that hold a line are divided by the host's pages; a
line over `ratio`, on `min_pages` pages or more, is boilerplate and goes from
every page of the host.  Pages of one host with equal texts count as one page,
so copies of a document, which are for document dedup to judge, do not turn
its lines into boilerplate.

Lines are compared without the blanks at their ends; blank lines are neither
counted nor dropped.  What crosses the network is a pair of hashes for each
line and page; the lines whose hashes are frequent are then counted once more by
themselves.  A host has at most (lines a page) / ratio boilerplate lines, so
they go back to the pages as one bounded array a host.

Defined results: a null text has no lines and stays null; rows with a null
host form one host; repeated rows count as one page and lose the same lines;
a page whose lines all go has an empty text; an empty table gives no rows;
columns named n_lines or n_dropped give way, other names never clash.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .storage import free_name, materialise

_BLANKS = " \t\r"


@dataclass(frozen=True)
class LineRules:
    ratio: float = 0.1
    min_pages: int = 4


def _trimmed(line: Column) -> Column:
    return F.trim(line, F.lit(_BLANKS))


def _lines(text: Column) -> Column:
    """The lines of a text that are not blank, trimmed."""
    return F.filter(F.transform(F.split(text, "\n", -1), _trimmed), lambda line: line != "")


def boilerplate(docs: DataFrame, text_col: str = "text", host_col: str = "source", rules: LineRules = LineRules()) -> DataFrame:
    """(host, line, pages, host_pages) of each boilerplate line."""
    rows = docs.select(F.col(host_col).cast("string").alias("host"), F.col(text_col).alias("text")).where("text is not null")
    page = F.unhex(F.md5("text")).alias("page")
    pages = rows.select("host", page, F.array_distinct(F.transform(_lines(F.col("text")), lambda x: F.xxhash64(x))).alias("keys"))
    # copies collapse to one page; (host, page) pairs also give the host's page total
    distinct = materialise(pages.select("host", "page", F.explode_outer("keys").alias("line_key")).distinct(), "lines")
    totals = materialise(distinct.select("host", "page").distinct().groupBy("host").agg(F.count("*").alias("host_pages")).withColumnRenamed("host", "named"), "hosts")

    def over(counts: DataFrame) -> DataFrame:
        frequent = counts.where(F.col("pages") >= rules.min_pages).join(totals, F.col("host").eqNullSafe(F.col("named")))
        return frequent.where(F.col("pages") > F.lit(rules.ratio) * F.col("host_pages")).drop("named")

    keys = over(distinct.where("line_key is not null").groupBy("host", "line_key").agg(F.count("*").alias("pages")))
    # lines that share a hash are counted together above, so every boilerplate line is among these; now each by itself
    by_host = materialise(keys.groupBy("host").agg(F.collect_set("line_key").alias("held")).withColumnRenamed("host", "named"), "line-keys")
    again = rows.join(by_host, F.col("host").eqNullSafe(F.col("named")))
    lines = F.array_distinct(F.filter(_lines(F.col("text")), lambda x: F.array_contains("held", F.xxhash64(x))))
    counted = again.select("host", page, F.explode(lines).alias("line")).distinct().groupBy("host", "line").agg(F.count("*").alias("pages"))
    return over(counted).select("host", "line", "pages", "host_pages")


def drop_boilerplate(docs: DataFrame, text_col: str = "text", host_col: str = "source", rules: LineRules = LineRules()) -> DataFrame:
    """`docs` with boilerplate lines cut from the text, and how many lines each had and lost.

    Columns of `docs` named n_lines or n_dropped give way to these.
    """
    docs = docs.select([c for c in docs.columns if c not in ("n_lines", "n_dropped")])
    found = boilerplate(docs, text_col, host_col, rules)
    drop, host, left = (free_name(docs, f"line_{x}") for x in ("drop", "host", "left"))
    by_host = materialise(found.groupBy("host").agg(F.sort_array(F.collect_set("line")).alias("dropped")), "boilerplate").toDF(host, drop)
    joined = docs.join(by_host, F.col(host_col).cast("string").eqNullSafe(F.col(host)), "left")
    parts = F.split(F.col(text_col), "\n", -1)
    stays = lambda line: ~F.array_contains(F.col(drop), _trimmed(line))
    kept = F.when(F.col(drop).isNull(), parts).otherwise(F.filter(parts, stays))
    no_text = F.col(text_col).isNull()
    lines = F.when(no_text, 0).otherwise(F.size(F.filter(parts, lambda line: _trimmed(line) != ""))).cast("long")
    dropped = F.when(no_text, 0).otherwise(F.size(parts) - F.size(left)).cast("long")
    cut = joined.withColumn(left, kept).withColumn("n_lines", lines).withColumn("n_dropped", dropped)
    return cut.withColumn(text_col, F.array_join(left, "\n")).select(*docs.columns, "n_lines", "n_dropped")
