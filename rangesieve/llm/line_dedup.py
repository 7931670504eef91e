"""Line dedup by site-relative frequency, on DataFrame functions alone.

A page's markup is cut into lines of text. Per host, the pages that contain a line are divided by the host's pages;
a line above RATIO is boilerplate of that host and dropped from its pages. A line needs PAGES pages at least, so that
a host of one page keeps its text.

The markup is cut once; the lines are written to the shared folder and read for counting and for dropping. Lines are
counted by hash after one row per page and distinct line; counts combine before the shuffle, so a hot host costs no more
than its distinct lines. The boilerplate of a host is a bounded set: shares of more than RATIO add up to
at most the mean number of lines of a page, so a host has at most mean / RATIO such lines, and they travel as one
array. Hosts with so many pages that they stand out (a bounded list) meet their array in SALTS places.

Defined cases: null or unreadable url gives the empty host, which is a site like others; null markup has no lines;
repeated rows are separate pages; a line that repeats within a page counts once and is dropped at every place; empty
tables give no rows; extra columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rangesieve.llm.common import materialise, own, shuffle_width

RATIO = 0.3
PAGES = 3
SALTS = 64
HOT = 8  # hosts a shuffle partition that are listed as hot

_HIDDEN = r"(?is)<(script|style)\b[^>]*>.*?</\1\s*>"
_COMMENT = r"(?s)<!--.*?-->"
_BREAK = r"(?i)<(?:/?(?:p|div|li|ul|ol|h[1-6]|tr|table|section|article|nav|header|footer|title|head|body|main|aside|pre|blockquote)\b[^>]*|br\s*/?)>"
_TAG = r"<[^>]*>"


def host_of(url: Column) -> Column:
    return F.lower(F.coalesce(F.regexp_extract(url, r"^[A-Za-z][A-Za-z0-9+.-]*://(?:[^/@?#]*@)?([^/:?#]+)", 1), F.lit("")))


def page_lines(html: Column) -> Column:
    """The visible lines of a page, trimmed, without empty ones."""
    t = F.regexp_replace(F.coalesce(html, F.lit("")), _HIDDEN, "")
    t = F.regexp_replace(F.regexp_replace(F.regexp_replace(t, _COMMENT, ""), _BREAK, "\n"), _TAG, "")
    for entity, char in (("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "'"), ("&nbsp;", " "), ("&amp;", "&")):
        t = F.replace(t, F.lit(entity), F.lit(char))
    return F.filter(F.transform(F.split(t, "\n"), lambda x: F.trim(F.regexp_replace(x, r"[ \t\r]+", " "))), lambda x: x != "")


def host_boilerplate(paged: DataFrame, ratio: float = RATIO, pages: int = PAGES) -> DataFrame:
    """host, common: hashes of the lines above the ratio, from rows (host, hashes)."""
    lines = paged.select("host", F.explode(F.array_distinct("hashes")).alias("line"))
    counts = lines.groupBy("host", "line").agg(F.count("*").alias("n")).where(F.col("n") >= pages)
    totals = paged.groupBy("host").agg(F.count("*").alias("total")).withColumnRenamed("host", "h_")
    over = counts.join(totals, F.col("host") == F.col("h_")).where(F.col("n") > F.col("total") * ratio)
    return over.groupBy("host").agg(F.array_sort(F.collect_list("line")).alias("common"))


def dedup_lines(pages: DataFrame, ratio: float = RATIO, least: int = PAGES) -> DataFrame:
    """page_id, host, n_lines, n_dropped, text (the kept lines) of every page."""
    read = own(pages, "page_id", "url", "html").select("page_id", host_of(F.col("url")).alias("host"), page_lines(F.col("html")).alias("lines"))
    read = materialise(read, "lines")
    hashed = F.transform("lines", lambda x: F.xxhash64(x))
    common = host_boilerplate(read.select("host", hashed.alias("hashes")), ratio, least).withColumnRenamed("host", "h_")
    # At most HOT hosts a partition have more pages than this.
    most = read.count() // (HOT * shuffle_width(pages.sparkSession))
    hot = [r.host for r in read.groupBy("host").agg(F.count("*").alias("n")).where(F.col("n") > max(most, SALTS)).collect()]
    salts = F.when(F.col("host").isin(hot), F.lit(SALTS)).otherwise(F.lit(1)) if hot else F.lit(1)
    common = common.withColumn("host", F.col("h_")).withColumn("s_", F.explode(F.sequence(F.lit(0), salts - 1))).drop("host")
    salted = read.select("page_id", "host", "lines", F.pmod(F.xxhash64("page_id", F.size("lines")), salts).cast("int").alias("salt"))
    joined = salted.join(common, (F.col("host") == F.col("h_")) & (F.col("salt") == F.col("s_")), "left")
    kept = F.filter("lines", lambda x: F.col("common").isNull() | ~F.array_contains(F.col("common"), F.xxhash64(x)))
    return joined.select("page_id", "host", F.size("lines").cast("long").alias("n_lines"), kept.alias("kept")).select(
        "page_id", "host", "n_lines", (F.col("n_lines") - F.size("kept")).cast("long").alias("n_dropped"), F.array_join("kept", "\n").alias("text")
    )


ORACLE = rf"""
WITH stripped AS (
  SELECT page_id, row_number() OVER () AS r,
         lower(coalesce(regexp_extract(url, '^[A-Za-z][A-Za-z0-9+.-]*://(?:[^/@?#]*@)?([^/:?#]+)', 1), '')) AS host,
         regexp_replace(regexp_replace(regexp_replace(regexp_replace(regexp_replace(coalesce(html, ''),
           '(?is)<script\b[^>]*>.*?</script\s*>', '', 'g'), '(?is)<style\b[^>]*>.*?</style\s*>', '', 'g'),
           '{_COMMENT}', '', 'g'), '{_BREAK}', chr(10), 'g'), '{_TAG}', '', 'g') AS t
  FROM pages),
decoded AS (
  SELECT page_id, r, host, replace(replace(replace(replace(replace(replace(t, '&lt;', '<'), '&gt;', '>'), '&quot;', '"'), '&#39;', ''''), '&nbsp;', ' '), '&amp;', '&') AS t
  FROM stripped),
lined AS (
  SELECT page_id, r, host, list_filter(list_transform(string_split(t, chr(10)), lambda x: trim(regexp_replace(x, '[ \t\r]+', ' ', 'g'))), lambda x: x <> '') AS lines
  FROM decoded),
total AS (SELECT host, count(*) AS total FROM lined GROUP BY host),
cnt AS (SELECT host, line, count(*) AS n FROM (SELECT host, unnest(list_distinct(lines)) AS line FROM lined) GROUP BY ALL),
bad AS (SELECT host, list(line) AS common FROM cnt JOIN total USING (host) WHERE n >= {PAGES} AND n > total * {RATIO} GROUP BY host),
kept AS (SELECT page_id, host, lines, list_filter(lines, lambda x: common IS NULL OR NOT list_contains(common, x)) AS kept FROM lined LEFT JOIN bad USING (host))
SELECT page_id, host, len(lines)::BIGINT AS n_lines, (len(lines) - len(kept))::BIGINT AS n_dropped, array_to_string(kept, chr(10)) AS text FROM kept
"""
