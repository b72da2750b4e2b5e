"""Line dedup by site-relative frequency, in DataFrame functions only.

Lines are grouped by host: the pages of the host that hold a line are divided by all pages of the host, and lines above a boilerplate
ratio go from every page of that host. Only 64-bit line hashes are counted and joined; texts are read twice, and shuffled only where the lines to drop are too many to broadcast.

Lines of a page are its html without script and style elements and comments, cut at tags and line ends, trimmed of white space; empty
lines are no lines. A line counts once a page. The ratio holds for hosts of any size; a line must stand on min_holders pages (2 if not said otherwise), since
a line of one page alone repeats nothing. A url
without "://", or none, belongs to the host "". Rows without page_id are pages of their own. Repeated rows are pages of their own too: each counts.
A null html has no lines. Empty tables give empty results. Columns of the input other than the three named are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .store import written
from .url_filter import url_host

RATIO, MIN_HOLDERS = 0.3, 2
#: Hosts of more pages are hot: their totals are broadcast (at most one for each so many pages of the input), so that their lines stay spread.
HOT_HOST = 100_000
#: Up to so many line hashes the lines to drop are broadcast; beyond it pages and lines are joined with this many salts for each host.
BROADCAST_LINES, SALTS = 1_000_000, 64
_CUT = r"(?is)<script\b.*?</script[ \t\n\r\f]*>|<style\b.*?</style[ \t\n\r\f]*>|<!--.*?-->|<[^>]*>|[\n\r]+"


def html_lines(html: Column) -> Column:
    cut = F.split(F.coalesce(html, F.lit("")), _CUT)
    return F.filter(F.transform(cut, lambda x: F.btrim(x, F.lit(" \t\n\r\f"))), lambda x: x != "")


def frequent_lines(hashed: DataFrame, ratio: float, min_holders: int = MIN_HOLDERS) -> DataFrame:
    """host, line (hash), n_pages, host_pages of the lines above the ratio, for rows (host, lines array of distinct hashes)."""
    totals = written(hashed.groupBy("host").agg(F.count("*").alias("host_pages")), "host-pages")
    held = hashed.select("host", F.explode_outer("lines").alias("line")).filter("line is not null").groupBy("host", "line").agg(F.count("*").alias("n_pages")).filter(F.col("n_pages") >= min_holders)
    hot = totals.filter(F.col("host_pages") > HOT_HOST).select("host", F.col("host_pages").alias("_hot"))
    told = held.join(F.broadcast(hot), "host", "left")
    # Lines of hot hosts know their total: they go to the join with the others by a key of their own that nothing matches, and so to all tasks alike.
    key = F.when(F.col("_hot").isNull(), F.struct("host", F.lit(0).cast("long").alias("spread"))).otherwise(F.struct("host", F.col("line").bitwiseOR(F.lit(1)).alias("spread")))
    others = totals.filter(F.col("host_pages") <= HOT_HOST).select(F.struct("host", F.lit(0).cast("long").alias("spread")).alias("_key"), "host_pages")
    told = told.withColumn("_key", key).join(others, "_key", "left").withColumn("host_pages", F.coalesce("_hot", "host_pages"))
    return told.filter(F.col("n_pages") > F.col("host_pages") * F.lit(ratio)).select("host", "line", "n_pages", "host_pages")


def drop_boilerplate(pages: DataFrame, ratio: float = RATIO, id_col: str = "page_id", url_col: str = "url", html_col: str = "html", min_holders: int = MIN_HOLDERS) -> DataFrame:
    """id_col, host, n_lines, n_dropped, text (the lines that stay, joined by line ends) for every page."""
    lined = pages.select(F.col(id_col).alias("page_id"), url_host(F.col(url_col)).alias("host"), html_lines(F.col(html_col)).alias("lines"))
    hashed = lined.select("host", F.array_distinct(F.transform("lines", lambda x: F.xxhash64(x))).alias("lines"))
    # At most 1 / ratio times the mean number of lines of a page can be above the ratio on a host, so a host's set is short.
    by_host = written(frequent_lines(hashed, ratio, min_holders).groupBy("host").agg(F.collect_set("line").alias("_drop")), "boilerplate")
    if (by_host.agg(F.sum(F.size("_drop") + 4)).first()[0] or 0) <= BROADCAST_LINES:
        judged = lined.join(F.broadcast(by_host), "host", "left")
    else:  # pages of one host go to as many tasks as there are salts
        salted = by_host.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
        judged = lined.withColumn("_salt", F.pmod(F.xxhash64("page_id", F.size("lines")), F.lit(SALTS)).cast("int")).join(salted, ["host", "_salt"], "left")
    judged = judged.withColumn("_kept", F.when(F.col("_drop").isNull(), F.col("lines")).otherwise(F.filter("lines", lambda x: ~F.array_contains(F.col("_drop"), F.xxhash64(x)))))
    return judged.select(F.col("page_id").alias(id_col), "host", F.size("lines").alias("n_lines"), (F.size("lines") - F.size("_kept")).alias("n_dropped"), F.array_join("_kept", "\n").alias("text"))
