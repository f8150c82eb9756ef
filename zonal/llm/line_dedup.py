"""Line dedup by site-relative frequency.

Pages are grouped by host; for each (host, line) the pages that contain the line are divided
by the host's pages, and lines above ``max_ratio`` are boilerplate and dropped. Lines are
compared trimmed; empty lines always stay. So that a small host's only page isn't all
boilerplate, a line must also occur on ``min_pages`` pages of its host. Lines of fewer than
``min_words`` words always stay.

Plan: a page's distinct lines are aggregated partially before the exchange on (host, line),
so a line of a huge host moves once per split, not once per page. What is boilerplate is
written once and goes back to the occurrences by hash: occurrences travel as a page id and a
hash, and those of a line on very many pages are dealt over many tasks. What a page meets
there, at most its own lines, is compared by host and text once more before anything is
dropped.

Defined results: null or malformed URLs share the host "" ; null text has no lines and comes
back as null; pages repeated under an id count as pages of their own in the statistics and
are cleaned alike; a page can end empty; empty tables give empty results.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import join_by_key, materialize, word_count


def host_of(url: Column) -> Column:
    return F.lower(F.regexp_extract(F.coalesce(url.cast("string"), F.lit("")), r"^[A-Za-z][A-Za-z0-9+.-]*://([^/?#]*)", 1))


#: What a page doesn't show, and the tags at which its text breaks into lines; patterns mean the
#: same to Java and to RE2.
REST = r"(?:[\t\n\r\f /][^>]*)?>"
HIDDEN = r"(?is)<!--.*?(?:-->|\z)" + "".join(rf"|<{tag}{REST}.*?(?:</{tag}[\t\n\r\f ]*>|\z)" for tag in ("script", "style", "template", "noscript"))
BLOCK = (
    r"(?i)</?(?:address|article|aside|blockquote|body|br|caption|d[dlt]|div|fieldset|figcaption|figure|footer|form|h[1-6r]|head|header|html|legend"
    rf"|li|main|nav|ol|option|p|pre|section|select|table|tbody|t[dhr]|tfoot|thead|title|ul){REST}"
)
INLINE = r"</?[A-Za-z][^>]*>|<![^>]*>"
ENTITIES = {"&nbsp;": " ", "&lt;": "<", "&gt;": ">", "&quot;": '"', "&#39;": "'", "&amp;": "&"}


def rendered(html: Column) -> Column:
    """The text that a page shows, a line for every block, trimmed and not empty; null stays null."""
    text = F.regexp_replace(F.regexp_replace(F.regexp_replace(html, HIDDEN, ""), BLOCK, "\n"), INLINE, "")
    for name, char in ENTITIES.items():
        text = F.replace(text, F.lit(name), F.lit(char))
    lines = F.transform(F.split(text, "\n"), lambda x: F.btrim(x, F.lit(" \t\r\f")))
    return F.array_join(F.filter(lines, lambda x: x != ""), "\n")


def rendered_sql(html: str) -> str:
    """The same as an expression of DuckDB."""
    quote = lambda x: x.replace("'", "''")
    text = f"regexp_replace(regexp_replace(regexp_replace({html}, '{quote(HIDDEN)}', '', 'g'), '{quote(BLOCK)}', chr(10), 'g'), '{quote(INLINE)}', '', 'g')"
    for name, char in ENTITIES.items():
        text = f"replace({text}, '{quote(name)}', '{quote(char)}')"
    lines = f"list_filter(list_transform(string_split({text}, chr(10)), lambda x: trim(x, ' ' || chr(9) || chr(13) || chr(12))), lambda x: x <> '')"
    return f"case when {html} is not null then coalesce(array_to_string({lines}, chr(10)), '') end"


def boilerplate_lines(pages: DataFrame, max_ratio: float, min_pages: int, min_words: int = 0) -> DataFrame:
    """host, line, n_pages, host_pages of boilerplate; ``pages`` has host and lines."""
    totals = pages.groupBy("host").agg(F.count(F.lit(1)).alias("host_pages"), F.sum(F.greatest(F.size("lines"), F.lit(0))).alias("host_lines"))
    totals = materialize(totals, "line-totals")
    seen = pages.select("host", F.explode(F.array_distinct(F.transform("lines", F.trim))).alias("line")).where("line <> ''")
    counts = seen.groupBy("host", "line").agg(F.count(F.lit(1)).alias("n_pages")).where(F.col("n_pages") >= min_pages)
    if min_words:
        counts = counts.where(word_count(F.col("line")) >= min_words)
    met = join_by_key(counts, totals, ["host"], "host_lines", ["line"])
    return met.where(F.col("n_pages") > F.col("host_pages") * F.lit(max_ratio)).select("host", "line", "n_pages", "host_pages")


def drop_boilerplate(
    pages: DataFrame,
    host: Column,
    id_col: str,
    text_col: str,
    max_ratio: float = 0.1,
    min_pages: int = 3,
    min_words: int = 0,
) -> DataFrame:
    """All columns of ``pages`` with ``text_col`` cleaned, and __n_lines and __n_dropped."""
    work = pages.select(F.col(id_col).alias("__id"), host.alias("host"), F.split(F.col(text_col), "\n").alias("lines"))
    key = F.xxhash64("host", "line").alias("h")
    bad = boilerplate_lines(work, max_ratio, min_pages, min_words).select(key, F.struct("host", "line").alias("bad"), "n_pages")
    bad = materialize(bad.groupBy("h").agg(F.collect_set("bad").alias("bad"), F.sum("n_pages").alias("n")), "line-bad")
    met = work.select("__id", "host", F.explode(F.array_distinct(F.transform("lines", F.trim))).alias("line")).where("line <> ''")
    hits = join_by_key(met.select("__id", key), bad, ["h"], "n", ["__id"]).groupBy("__id").agg(F.flatten(F.collect_set("bad")).alias("__bad"))
    lines = F.split(F.col(text_col), "\n")
    joined = pages.join(hits, F.col(id_col).eqNullSafe(F.col("__id")), "left")
    kept = F.when(F.col("__bad").isNull(), lines).otherwise(F.filter(lines, lambda x: ~F.array_contains(F.col("__bad"), F.struct(host.alias("host"), F.trim(x).alias("line")))))
    joined = joined.withColumn("__kept", kept).withColumn("__n_lines", F.coalesce(F.size(lines), F.lit(0)).cast("long"))
    joined = joined.withColumn("__n_dropped", F.col("__n_lines") - F.greatest(F.size("__kept"), F.lit(0)))
    text = F.when(F.col(text_col).isNotNull(), F.array_join("__kept", "\n"))
    return joined.withColumn(text_col, text).drop("__id", "__bad", "__kept")
