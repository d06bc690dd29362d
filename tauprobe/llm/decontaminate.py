"""Benchmark decontamination over a distributed positional inverted index, in DataFrame functions only.

`build_index` stores the postings (term, doc, pos) of a vocabulary, here that of the test items, in the shared folder, with
one row more for each document under the empty term that holds its id and number of words. `phrases` finds every window of
consecutive item words: for each window the rarest of its terms (by postings in the index) is the pivot; the pivots'
postings, moved back by the pivot's place in the item, give alignments of item and document; the postings of the other terms
of the pivot's windows, moved back likewise, are intersected with them; runs of matched places as long as a window are the
occurrences. `near` finds the places where all terms of a query lie within a span, in any order.

Everything is an equi-join or an aggregation. What is broadcast is counted first and only sent if it is small; beyond that
the same join is shuffled. A passage in very many documents gives as many rows as it has occurrences.

Defined results: a null text has no words, as an empty one; an item without words has no window, one of fewer words than a
window is one window; very long texts count whole; repeated rows give repeated results (each row is a document of its own in
the index); equal item texts all count; an item without id marks words but is not listed; empty tables give no rows, or no
hits; only the named columns are read.
"""

from __future__ import annotations

import string
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from tauprobe.llm.arrow_kernels import small
from tauprobe.session import materialize

#: Word characters before lower case is taken: ASCII letters and digits, and all that is not ASCII.
WORD = r"[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"


def ascii_lower(word: Column) -> Column:
    """Lower case for A-Z alone. Words of ASCII take the fast function."""
    return F.when(F.octet_length(word) == F.char_length(word), F.lower(word)).otherwise(F.translate(word, string.ascii_uppercase, string.ascii_lowercase))


def raw_words(text: Column) -> Column:
    return F.regexp_extract_all(F.coalesce(text.cast("string"), F.lit("")), F.lit(WORD), 0)


@dataclass(frozen=True)
class Index:
    postings: DataFrame  # term, doc, pos
    documents: DataFrame  # doc, id, n_words

    def frequencies(self) -> DataFrame:
        return self.postings.groupBy("term").agg(F.count(F.lit(1)).alias("tf"))


def build_index(df: DataFrame, vocabulary: DataFrame | None = None, id_col: str = "doc_id", text_col: str = "text") -> Index:
    """Index of the texts of df, over the terms of the vocabulary (column term), or over all terms."""
    rows = df.select(F.monotonically_increasing_id().alias("doc"), F.col(id_col).alias("id"), raw_words(F.col(text_col)).alias("words"))
    each = rows.select("doc", "id", F.size("words").alias("n"), F.posexplode(F.concat(F.array(F.lit("")), F.col("words"))).alias("pos", "word"))
    each = each.select("doc", F.when(F.col("pos") == 0, F.col("id")).alias("id"), F.when(F.col("pos") == 0, F.col("n")).alias("n_words"), (F.col("pos") - 1).alias("pos"), ascii_lower(F.col("word")).alias("term"))
    if vocabulary is not None:
        wanted = vocabulary.select("term").union(df.sparkSession.createDataFrame([("",)], "term string")).distinct()
        each = each.join(small(materialize(wanted, "vocabulary")), "term")
    stored = materialize(each.select("term", "doc", "pos", "id", "n_words"), "postings")
    return Index(stored.where("term <> ''").select("term", "doc", "pos"), stored.where("term = ''").select("doc", "id", F.col("n_words").cast("bigint").alias("n_words")))


def item_words(items: DataFrame, id_col: str = "item_id", text_col: str = "text") -> DataFrame:
    """Rows (item, item_id, length, j, term): the words of each item; item numbers the rows."""
    rows = items.select(F.monotonically_increasing_id().alias("item"), F.col(id_col).alias("item_id"), raw_words(F.col(text_col)).alias("words"))
    each = rows.select("item", "item_id", F.size("words").alias("length"), F.posexplode("words").alias("j", "word"))
    return materialize(each.select("item", "item_id", "length", "j", ascii_lower(F.col("word")).alias("term")), "item-words")


def _pivots(words: DataFrame, frequencies: DataFrame, window: int) -> DataFrame:
    """Rows (term, j, item, width, need): the places that are the rarest of a window, and the places and terms of those windows."""
    counted = words.join(small(frequencies), "term", "left").select("item", "length", "j", "term", F.coalesce("tf", F.lit(0)).alias("tf"))
    width = F.least(F.col("length"), F.lit(window))
    starts = F.sequence(F.greatest(F.lit(0), F.col("j") - width + 1), F.least(F.col("j"), F.col("length") - width))
    each = counted.select("item", "j", "term", "tf", width.alias("width"), F.explode(starts).alias("start"))
    windows = each.groupBy("item", "start", "width").agg(F.min(F.struct("tf", "j", "term")).alias("rarest"), F.collect_list(F.struct("j", "term")).alias("need"))
    alive = windows.where("rarest.tf > 0")  # a term that no document has rules the window out
    grouped = alive.groupBy("item", "width", F.col("rarest.term").alias("term"), F.col("rarest.j").alias("j"))
    return grouped.agg(F.array_distinct(F.flatten(F.collect_list("need"))).alias("need"))


def phrases(index: Index, words: DataFrame, window: int = 13) -> DataFrame:
    """Rows (doc, item, first, last): the runs of document words covered by occurrences of the item's windows."""
    pivots = materialize(_pivots(words, materialize(index.frequencies(), "frequencies"), window), "pivots")
    met = index.postings.join(small(pivots), "term").select("doc", "item", "width", (F.col("pos") - F.col("j")).alias("shift"), "need")
    aligned = materialize(met, "alignments")
    needed = aligned.select("doc", "item", "width", "shift", F.explode("need").alias("n"))
    needed = needed.select("doc", "item", "width", "shift", "n.j", (F.col("shift") + F.col("n.j")).alias("pos"), "n.term").distinct()
    within = index.postings.join(small(aligned.select("doc").distinct()), "doc", "left_semi")
    matched = needed.join(within, ["doc", "pos", "term"], "left_semi").select("doc", "item", "width", "shift", "j")
    order = W.partitionBy("doc", "item", "width", "shift").orderBy("j")
    runs = matched.select("*", (F.col("j") - F.row_number().over(order)).alias("run")).groupBy("doc", "item", "width", "shift", "run").agg(F.min("j").alias("a"), F.max("j").alias("b"))
    return runs.where("b - a + 1 >= width").select("doc", "item", (F.col("shift") + F.col("a")).alias("first"), (F.col("shift") + F.col("b")).alias("last"))


def contamination(df: DataFrame, items: DataFrame, window: int = 13, share: int = 20, id_col: str = "doc_id", text_col: str = "text", item_id: str = "item_id", item_text: str = "text") -> DataFrame:
    """Rows (id, n_words, n_hit, n_items, items_sha256, contaminated): one for each row of df."""
    words = item_words(items, item_id, item_text)
    index = build_index(df, words.select("term"), id_col, text_col)
    found = materialize(phrases(index, words, window), "occurrences")
    places = found.select("doc", F.explode(F.sequence("first", "last")).alias("pos")).distinct().groupBy("doc").agg(F.count(F.lit(1)).alias("n_hit"))
    names = words.select("item", F.col("item_id").cast("string").alias("name")).distinct().where("name is not null")
    listed = found.select("doc", "item").distinct().join(small(names), "item").groupBy("doc").agg(F.sort_array(F.collect_set("name")).alias("names"))
    joined = index.documents.join(places, "doc", "left").join(listed, "doc", "left")
    hits, names = F.coalesce("n_hit", F.lit(0)), F.coalesce("names", F.array().cast("array<string>"))
    return joined.select(
        "id", "n_words", hits.alias("n_hit"), F.size(names).cast("bigint").alias("n_items"), F.sha2(F.array_join(names, ","), 256).alias("items_sha256"),
        ((hits > 0) & (share * hits >= F.col("n_words"))).alias("contaminated"),
    )


def near(index: Index, queries: DataFrame, span: int = 20, id_col: str = "item_id", text_col: str = "text") -> DataFrame:
    """Rows (id, item_id, first): places of a query's rarest term around which all its terms lie, in any order, within span words.

    Within span means that the last of them comes less than span places after the first. A term that a query repeats must
    lie there as often. A query without words, or with more of them than span, is found nowhere; a query without id is not
    listed; rows of one document id are documents of their own, each with its places.
    """
    words = item_words(queries, id_col, text_col).where("item_id is not null").groupBy("item", "item_id", "term").agg(F.count(F.lit(1)).alias("times"))
    counted = words.join(index.frequencies(), "term", "left").select("item", "item_id", "term", "times", F.coalesce("tf", F.lit(0)).alias("tf"))
    wanted = F.sort_array(F.collect_list(F.struct("term", "times")))
    plans = counted.groupBy("item", "item_id").agg(F.min(F.struct("tf", "term")).alias("rarest"), wanted.alias("wanted"), F.sum("times").alias("size"))
    plans = plans.where((F.col("rarest.tf") > 0) & (F.col("size") <= span)).select("item", "item_id", F.col("rarest.term").alias("term"), "wanted")
    at = index.postings.join(plans, "term").select("doc", F.col("pos").alias("first"), "item", "item_id", "wanted", F.explode("wanted.term").alias("term"))
    at = at.select("*", F.explode(F.array(*[F.floor(F.col("first") / span) + k for k in (-1, 0, 1)])).alias("cell"))
    there = index.postings.select("doc", "term", F.col("pos").alias("other"), F.floor(F.col("pos") / span).alias("cell"))
    met = at.join(there, ["doc", "term", "cell"]).where(F.abs(F.col("other") - F.col("first")) < span)
    # at most one place for each word around: some stretch of span words that holds the anchor has every term often enough
    around = met.groupBy("doc", "item", "item_id", "first", "wanted").agg(F.collect_set(F.struct(F.col("other").alias("p"), "term")).alias("there"))
    held = lambda start, w: F.size(F.filter("there", lambda x: (x["term"] == w["term"]) & (x["p"] >= start) & (x["p"] < start + span))) >= w["times"]
    whole = around.where(F.exists("there", lambda x: (x["p"] <= F.col("first")) & (x["p"] + span > F.col("first")) & F.forall("wanted", lambda w: held(x["p"], w))))
    return whole.join(index.documents, "doc").select("id", "item_id", "first")
