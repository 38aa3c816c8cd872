"""Benchmark decontamination over a distributed positional inverted index.

A benchmark item is cut into windows of consecutive words. The index stores, for the training documents, the
places (postings) of terms; a window is looked up from its rarest terms on: their posting lists are shifted by
the terms' offsets in the window and intersected, which leaves the places where the window may start. At those places
all its words are compared. Only built-in functions are used.

The index is built for the stated test set: which terms are the rarest is counted over all documents, and only the
postings of the ``anchors`` rarest terms of each window are stored, a few numbers for each. Storage follows the occurrences of
rare terms instead of all words. ``postings`` gives the full index for other uses, and ``proximity`` the documents where a
window's rarest terms lie close together in any order.

A row of the documents goes by its id and the hash of its text, so rows that repeat an id, or have none, are told apart.
The test set's tables are broadcast when they have at most ``broadcast_rows`` rows, else joined by a shuffle.

Edge cases: null texts have no words; items without words match nothing; an item shorter than a window is one window; ties in
rarity go to the earlier place in the window; repeated rows each get the hits of their own text; repeated items and windows count
once for an item; a very long text is held by one task as the array of its words, postings carry no text; an empty table on either side
leaves all documents clean; a null id is an id of its own; other columns, whatever their names, are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import ascii_lower, let, small_enough, written

# Fixed value: what divides words, once letters A to Z are lower-cased.
BETWEEN_WORDS = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"


def words_of(text: Column) -> Column:
    """The words of a text in order; an empty array for null."""
    return F.array_remove(F.split(ascii_lower(F.coalesce(text, F.lit(""))), BETWEEN_WORDS), "")


def windows_of(items: DataFrame, item_col: str, text_col: str, width: int) -> tuple[DataFrame, DataFrame]:
    """(window, phrase, size) for each distinct window, and (window, item_id) for the items it stems from. ``window`` is a number,
    ``phrase`` the words with a space between them."""
    w = items.select(F.col(item_col).alias("item_id"), words_of(F.col(text_col)).alias("w")).where(F.size("w") > 0)
    starts = F.sequence(F.lit(1), F.greatest(F.lit(1), F.size("w") - width + 1))
    cut = w.select("item_id", F.explode(starts).alias("s"), "w").select("item_id", F.slice("w", F.col("s"), F.lit(width)).alias("words"))
    cut = written(cut.select("item_id", F.array_join("words", " ").alias("phrase"), F.size("words").alias("size")).distinct(), "windows")
    numbered = written(cut.select("phrase", "size").distinct().withColumn("window", F.monotonically_increasing_id()), "numbered-windows")
    return numbered, written(cut.join(numbered, ["phrase", "size"]).select("window", "item_id"), "window-items")


def postings(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The full positional index: (term, doc_id, positions), positions rising from 0."""
    placed = docs.select(F.col(id_col).alias("doc_id"), F.posexplode(words_of(F.col(text_col))).alias("pos", "term"))
    return placed.groupBy("term", "doc_id").agg(F.sort_array(F.collect_list("pos")).alias("positions"))


class TestIndex:
    """Postings of the rarest terms of a test set's windows over all documents."""

    __test__ = False

    def __init__(self, docs: DataFrame, items: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text", *, width: int = 10, anchors: int = 2, broadcast_rows: int = 500_000):
        text = F.col(text_col)
        self.texts = docs.select(F.col(id_col).alias("doc_id"), F.xxhash64(text).alias("own"), text.alias("t"))
        self.id_col, self.anchors, self.broadcast_rows = id_col, anchors, broadcast_rows
        self.windows, self.items = windows_of(items, item_col, item_text_col, width)
        self.frequencies = written(self._count(), "term-counts")
        self.ranked = written(self._rank(), "ranked-terms")
        self.stored = written(self._store(), "postings")

    def _bounded(self, df: DataFrame) -> DataFrame:
        return F.broadcast(df) if small_enough(df, self.broadcast_rows) else df

    def _count(self) -> DataFrame:
        """(term, n): how often each test term occurs in the documents; terms that never do are left out."""
        terms = written(self.windows.select(F.explode(F.split("phrase", " ")).alias("term")).distinct(), "terms")
        return self.texts.select(F.explode(words_of(F.col("t"))).alias("term")).join(self._bounded(terms), "term").groupBy("term").agg(F.count(F.lit(1)).alias("n"))

    def _rank(self) -> DataFrame:
        """(window, anchors, rank, term, offset): the rarest terms of each window all of whose terms occur."""
        placed = self.windows.select("window", F.posexplode(F.split("phrase", " ")).alias("offset", "term")).join(self.frequencies, "term", "left")
        # Repeated terms of a window need one list only: the first place of each stands for all.
        firsts = placed.groupBy("window", "term").agg(F.min("offset").alias("offset"), F.max(F.coalesce("n", F.lit(0))).alias("n"))
        order = F.array_sort(F.collect_list(F.struct("n", "offset", "term")))
        ranked = firsts.groupBy("window").agg(order.alias("t")).where(F.col("t")[0]["n"] > 0).select("window", F.slice("t", 1, self.anchors).alias("t"))
        return ranked.select("window", F.size("t").alias("anchors"), F.posexplode("t").alias("rank", "a")).select("window", "anchors", "rank", F.col("a.term").alias("term"), F.col("a.offset").alias("offset"))

    def _store(self) -> DataFrame:
        """(term, doc_id, own, pos): a posting for each place of an anchor term."""
        needed = written(self.ranked.select("term").distinct(), "anchors")
        placed = self.texts.select("doc_id", "own", F.posexplode(words_of(F.col("t"))).alias("pos", "term"))
        return placed.join(self._bounded(needed), "term").select("term", "doc_id", "own", "pos")

    def _starts(self) -> DataFrame:
        """(doc_id, own, window, start): where the shifted lists of all anchors of a window meet."""
        lists = self.stored.join(self._bounded(self.ranked), "term").withColumn("start", F.col("pos") - F.col("offset")).where("start >= 0")
        met = lists.groupBy("doc_id", "own", "window", "start").agg(F.bit_or(F.expr("shiftleft(1, rank)")).alias("lists"), F.max("anchors").alias("anchors"))
        return met.where(F.col("lists") == F.expr("shiftleft(1, anchors) - 1")).select("doc_id", "own", "window", "start")

    def phrases(self) -> DataFrame:
        """(doc_id, own, window, start, size): every place where a whole window stands in a document."""
        starts = written(self._starts(), "starts").join(self._bounded(self.windows), "window")
        asked = starts.groupBy(F.col("doc_id").alias("row_id"), F.col("own").alias("row_own")).agg(F.collect_list(F.struct("window", "start", "size", "phrase")).alias("asked"))
        asked = written(asked, "asked-places")
        same = (F.col("own") == F.col("row_own")) & F.col("doc_id").eqNullSafe(F.col("row_id"))
        # Texts of documents without a place to look at are left out before the others are moved.
        texts = self.texts.join(self._bounded(asked.select("row_id", "row_own")), same, "left_semi")
        once = texts.dropDuplicates(["doc_id", "own"]) if self._repeats(asked) else texts
        right = let(words_of(F.col("t")), lambda w: F.filter("asked", lambda p: F.array_join(F.slice(w, p["start"] + 1, p["size"]), " ") == p["phrase"]))
        found = once.join(asked, same).select("doc_id", "own", F.explode(right).alias("p"))
        return found.select("doc_id", "own", "p.window", "p.start", "p.size")

    def _repeats(self, asked: DataFrame) -> bool:
        """Whether any row to look at stands in the documents more than once."""
        same = (F.col("own") == F.col("row_own")) & F.col("doc_id").eqNullSafe(F.col("row_id"))
        rows = self.texts.select("doc_id", "own").join(self._bounded(asked.select("row_id", "row_own")), same, "left_semi")
        return not rows.groupBy("doc_id", "own").count().where("count > 1").isEmpty()

    def proximity(self, span: int) -> DataFrame:
        """(doc_id, window): documents that hold all anchor terms of a window, in any order, within ``span`` words."""
        near = self.stored.join(self._bounded(self.ranked), "term")
        block = F.floor(F.col("pos") / span)
        dealt = near.withColumn("block", F.explode(F.array(block, block - 1)))
        lists = dealt.groupBy("doc_id", "own", "window", "block").agg(F.bit_or(F.expr("shiftleft(1, rank)")).alias("lists"), F.max("anchors").alias("anchors"), F.array_sort(F.collect_set(F.struct("pos", "rank"))).alias("places"))
        full = lists.where(F.col("lists") == F.expr("shiftleft(1, anchors) - 1"))
        within = F.exists("places", lambda a: F.size(F.array_distinct(F.transform(F.filter("places", lambda b: (b["pos"] >= a["pos"]) & (b["pos"] < a["pos"] + span)), lambda b: b["rank"]))) == F.col("anchors"))
        return full.where(within).select("doc_id", "window").distinct()

    def hits(self) -> DataFrame:
        """(doc_id, own, n_hit, item_ids): words of a row inside any window's occurrence, and the items met, sorted as strings."""
        found = written(self.phrases(), "phrases")
        # Occurrences of one document are merged from left to right: a word counts for the first one that covers it.
        spans = found.groupBy("doc_id", "own", "start").agg(F.max("size").alias("size"))
        rising = F.array_sort(F.collect_list(F.struct("start", (F.col("start") + F.col("size")).alias("end"))))
        zero = F.struct(F.lit(0).alias("end"), F.lit(0).cast("long").alias("n"))

        def add(acc: Column, s: Column) -> Column:
            more = F.greatest(F.lit(0), s["end"] - F.greatest(s["start"], acc["end"]))
            return F.struct(F.greatest(acc["end"], s["end"]).alias("end"), (acc["n"] + more).alias("n"))

        covered = spans.groupBy("doc_id", "own").agg(F.aggregate(rising, zero, add)["n"].alias("n_hit"))
        met = found.select("doc_id", "own", "window").distinct().join(self._bounded(self.items), "window")
        items = met.groupBy("doc_id", "own").agg(F.array_sort(F.collect_set(F.col("item_id").cast("string"))).alias("item_ids"))
        items = items.select(F.col("doc_id").alias("item_doc"), F.col("own").alias("item_own"), "item_ids")
        return covered.join(items, F.col("doc_id").eqNullSafe(F.col("item_doc")) & (F.col("own") == F.col("item_own")), "left").select("doc_id", "own", "n_hit", "item_ids")

    def report(self) -> DataFrame:
        """(id, n_words, n_hit, item_ids) for every document."""
        sizes = self.texts.select("doc_id", "own", F.size(words_of(F.col("t"))).cast("long").alias("n_words"))
        hits = written(self.hits(), "hits").select(F.col("doc_id").alias("hit_id"), F.col("own").alias("hit_own"), "n_hit", "item_ids")
        joined = sizes.join(hits, F.col("doc_id").eqNullSafe(F.col("hit_id")) & (F.col("own") == F.col("hit_own")), "left")
        return joined.select(F.col("doc_id").alias(self.id_col), "n_words", F.coalesce("n_hit", F.lit(0).cast("long")).alias("n_hit"), F.coalesce("item_ids", F.array().cast("array<string>")).alias("item_ids"))
