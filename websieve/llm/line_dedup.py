"""Boilerplate lines by their frequency relative to a site.

Pages are grouped by host. For each line of a host, the number of its pages that contain the line is divided
by the number of the host's pages; lines whose ratio exceeds a limit (and that stand on at least
``least_pages`` pages) are dropped from the pages of that host. Only built-in functions are used.

Page text crosses no shuffle for the counts: a page is reduced to the hashes of its distinct lines, counted
first within tasks, so a hot host or line costs one partial sum for each task. The lines to drop are sent to
all tasks as one list of hashes for each host when there are at most ``broadcast_lines`` of them, and the pages are
filtered in place; beyond that, (host, text, line) keys meet them in joins that Spark may split, with the same result.

Lines are compared after trimming white space; blank lines are neither counted nor dropped.

Where a group is a large share of the corpus, no line reaches a ratio fit for a site, and ``repeated`` finds the lines to drop
by what chance would repeat: a line of few words needs many texts, a long one only ``least_pages``. Copies of a text count
once, and texts must differ around the line, so that near copies of one text do not make its lines boilerplate.

Edge cases: null text stays null and has no lines; a null host is a host of its own; repeated page ids count as pages of their
own, and each loses the lines of its own host; a line at the ratio itself stays, one above it goes; a very long text is held whole by one task
with 8 bytes a line; an empty table gives an empty result; all columns of the input come back, whatever their names.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import fresh, small_enough, written

NO_HOST = "\0"


def line_key(line: Column) -> Column:
    return F.xxhash64(F.trim(line))


def line_keys(text: Column) -> Column:
    """The distinct keys of a text's lines, blank ones left out."""
    lines = F.filter(F.split(F.coalesce(text, F.lit("")), "\n"), lambda x: F.trim(x) != "")
    return F.array_distinct(F.transform(lines, lambda x: line_key(x)))


def boilerplate(pages: DataFrame, host_col: str, text_col: str, *, ratio: float, least_pages: int) -> DataFrame:
    """(host, line, pages, host_pages) for every line to drop; ``line`` is the key of a trimmed line."""
    host = F.coalesce(F.col(host_col).cast("string"), F.lit(NO_HOST))
    rows = pages.select(host.alias("host"), line_keys(F.col(text_col)).alias("lines"))
    # The host's own page count travels as one more key, so that pages are read and parsed once.
    counted = rows.select("host", F.explode(F.concat(F.transform("lines", lambda x: F.struct(x.alias("line"), F.lit(False).alias("all"))), F.array(F.struct(F.lit(0).cast("long").alias("line"), F.lit(True).alias("all"))))).alias("k"))
    counts = counted.groupBy("host", "k.line", "k.all").agg(F.count(F.lit(1)).alias("pages")).where((F.col("pages") >= least_pages) | F.col("all"))
    counts = written(counts, "host-lines")
    totals = counts.where("all").select("host", F.col("pages").alias("host_pages"))
    return counts.where(~F.col("all")).join(totals, "host").where(F.col("pages") > ratio * F.col("host_pages")).select("host", "line", "pages", "host_pages")


def contexts(text: Column) -> Column:
    """What tells texts apart: the smallest and the largest hash of its word trigrams, which near copies mostly share, and the hash of all."""
    words = F.filter(F.split(text, "[ \n]+"), lambda w: w != "")

    def sides(w: Column) -> Column:
        hashes = F.transform(F.sequence(F.lit(1), F.greatest(F.size(w) - 2, F.lit(1))), lambda i: F.xxhash64(F.get(w, i - 1), F.get(w, i), F.get(w, i + 1)))
        return F.transform(F.array(hashes), lambda h: F.array(F.array_min(h), F.array_max(h)))[0]

    return F.concat(F.transform(F.array(words), sides)[0], F.array(F.xxhash64(text)))


def repeated(pages: DataFrame, host_col: str, text_col: str, *, ratio: float = 0.2, per_word: float = 0.1, least_pages: int = 5, least_variety: float = 0.2, broadcast_lines: int = 1_000_000) -> DataFrame:
    """(host, line, pages, host_pages) for every line that repeats in its host beyond chance; pages are distinct texts.

    A line of n words must stand on more than ``ratio * per_word ** (n - 1)`` of the host's texts, and on ``least_pages`` of them.
    The texts with the line must show at least ``least_pages`` different contexts, and as many as the part ``least_variety`` of
    the texts: of texts that share more than the rest of their trigrams, one is a near copy of the other.
    """
    host = F.coalesce(F.col(host_col).cast("string"), F.lit(NO_HOST))
    text = F.col(text_col)
    lines = F.filter(F.split(F.coalesce(text, F.lit("")), "\n"), lambda x: F.trim(x) != "")
    n_words = lambda x: F.length(F.trim(x)) - F.length(F.replace(F.trim(x), F.lit(" "), F.lit(""))) + 1
    keyed = F.array_distinct(F.transform(lines, lambda x: F.struct(line_key(x).alias("line"), F.least(n_words(x), F.lit(50)).alias("words"))))
    counts = pages.select(host.alias("host"), F.explode(keyed).alias("k")).groupBy("host", "k.line", "k.words").agg(F.count(F.lit(1)).alias("rows"))
    often = written(counts.where(F.col("rows") >= least_pages).select("host", "line", "words"), "repeated-lines")
    side = F.broadcast(often) if small_enough(often, broadcast_lines) else often
    # Contexts come before the lines are dealt out, so that a text is hashed once.
    rows = pages.where(text.isNotNull()).select(host.alias("host"), contexts(text).alias("c"), line_keys(text).alias("lines"))
    entries = rows.select("host", "c", F.explode("lines").alias("line")).join(side, ["host", "line"])
    told = entries.select("host", "line", "words", F.posexplode("c").alias("kind", "sign")).distinct()
    n = lambda k: F.count_if(F.col("kind") == k)
    told = told.groupBy("host", "line", "words").agg(F.greatest(n(0), n(1)).alias("contexts"), n(2).alias("pages"))
    totals = pages.groupBy(host.alias("host")).agg(F.count_distinct(F.xxhash64(text)).alias("host_pages"))
    found = told.join(totals, "host").where((F.col("pages") >= least_pages) & (F.col("pages") > ratio * F.pow(F.lit(per_word), F.col("words") - 1) * F.col("host_pages")))
    return found.where((F.col("contexts") >= least_pages) & (F.col("contexts") >= least_variety * F.col("pages"))).select("host", "line", "pages", "host_pages")


def drop_lines(text: Column, keys: Column) -> Column:
    kept = F.filter(F.split(text, "\n"), lambda x: (F.trim(x) == "") | ~F.array_contains(keys, line_key(x)))
    return F.when(F.size(keys) > 0, F.array_join(kept, "\n")).otherwise(text)


def drop_boilerplate(pages: DataFrame, id_col: str = "page_id", host_col: str = "host", text_col: str = "text", *, ratio: float = 0.2, least_pages: int = 5, broadcast_lines: int = 100_000, found: DataFrame | None = None) -> DataFrame:
    """``pages`` with the boilerplate lines of each host dropped from ``text_col``."""
    found = boilerplate(pages, host_col, text_col, ratio=ratio, least_pages=least_pages) if found is None else found
    found = written(found, "boilerplate")
    own_host, own_text = F.coalesce(F.col(f"`{host_col}`").cast("string"), F.lit(NO_HOST)), F.col(f"`{text_col}`")
    host, own, gone = (fresh(name, pages.columns) for name in ("gone_host", "gone_own", "gone_lines"))
    if small_enough(found, broadcast_lines):
        lists = found.groupBy(F.col("host").alias(host)).agg(F.collect_list("line").alias(gone))
        joined = pages.join(F.broadcast(lists), own_host == F.col(host), "left")
    else:
        # What goes from a page follows from its host and text alone, so pages meet their list by these, whatever their ids.
        keys = pages.select(own_host.alias("host"), F.xxhash64(own_text).alias("own"), F.explode(line_keys(own_text)).alias("line"))
        lists = keys.join(found, ["host", "line"]).groupBy(F.col("host").alias(host), F.col("own").alias(own)).agg(F.collect_set("line").alias(gone))
        joined = pages.join(lists, (own_host == F.col(host)) & (F.xxhash64(own_text) == F.col(own)), "left")
    text = drop_lines(own_text, F.coalesce(F.col(gone), F.array().cast("array<long>")))
    return joined.select(*(text.alias(c) if c == text_col else F.col(f"`{c}`") for c in pages.columns))
