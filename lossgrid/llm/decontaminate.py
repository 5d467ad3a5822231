"""Benchmark decontamination with a positional inverted index.

Test phrases are ordered by how rare their terms are in the training data.  Postings
(term, document, position) are stored for the rarest terms of every phrase; the lists
of a phrase are shifted by the term's place in it and intersected, and what is left is
compared word by word with the words stored around the rarest one.  Only DataFrame
functions are used.

The terms looked up in one pass over the documents are at most ``TERMS``, which bounds
what is broadcast; a larger test set takes more passes.
"""

from __future__ import annotations

import string

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .store import Scratch, keyed

GAP = "[\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+"
TERMS = 200_000
#: Stands after the last word of a document in the index; its position is the length.
END = " "


def lower_ascii(text: Column) -> Column:
    """A-Z in lower case, nothing else changed."""
    slow = F.translate(text, string.ascii_uppercase, string.ascii_lowercase)
    return F.when(F.octet_length(text) == F.length(text), F.lower(text)).otherwise(slow)


def words_of(text: Column) -> Column:
    return F.array_remove(F.split(lower_ascii(F.coalesce(text.cast("string"), F.lit(""))), GAP), "")


def phrases_of(items: DataFrame, length: int) -> DataFrame:
    """(item_id, phrase, words): every run of ``length`` words of an item, or all its words if fewer.

    Items without words have none.
    """
    words = items.select("item_id", words_of(F.col("text")).alias("words")).where(F.size("words") > 0)
    last = F.greatest(F.lit(0), F.size("words") - length)
    rows = words.select("item_id", "words", F.explode(F.sequence(F.lit(1), last + 1)).alias("at"))
    rows = rows.select("item_id", F.slice("words", F.col("at"), F.lit(length)).alias("words"))
    return rows.select("item_id", F.concat_ws(" ", "words").alias("phrase"), "words").distinct()


class PositionalIndex:
    """Postings of training terms, in the shared folder."""

    def __init__(self, docs: DataFrame, scratch: Scratch):
        """``docs`` has doc_id and text; doc_id should tell documents apart."""
        self.docs, self.scratch, self.made = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), scratch, 0

    def _passes(self, terms: DataFrame) -> list[DataFrame]:
        n = max(1, -(-terms.count() // TERMS))
        return [terms.where(F.pmod(F.xxhash64("term"), F.lit(n)) == k) for k in range(n)]

    def frequencies(self, terms: DataFrame) -> DataFrame:
        """(term, n): occurrences in all documents of those of ``terms`` that occur."""
        self.made += 1
        tokens = self.docs.select(F.explode(words_of(F.col("text"))).alias("term"))
        parts = [tokens.join(F.broadcast(some), "term").groupBy("term").agg(F.count(F.lit(1)).alias("n")) for some in self._passes(terms)]
        out = parts[0]
        for part in parts[1:]:
            out = out.union(part)
        return self.scratch.save(out, f"frequencies-{self.made}")

    def postings(self, terms: DataFrame, around: int) -> DataFrame:
        """(term, doc_id, pos, lo, context): every occurrence of ``terms`` (term, anchor).

        Anchors carry the words up to ``around`` places before and after them, the first at place
        lo.  Each document also has one row for END, whatever its words.
        """
        self.made += 1
        words = self.docs.select("doc_id", F.concat(words_of(F.col("text")), F.array(F.lit(END))).alias("words"))
        tokens = words.select("doc_id", "words", F.posexplode("words").alias("pos", "term"))
        lo = F.greatest(F.lit(0), F.col("pos") - around)
        context = F.when(F.col("anchor"), F.slice("words", lo + 1, F.col("pos") - lo + around + 1))
        ends = self.docs.sparkSession.createDataFrame([(END, False)], "term string, anchor boolean")
        out = None
        for k, some in enumerate(self._passes(terms)):
            some = some.union(ends) if k == 0 else some
            part = tokens.join(F.broadcast(some), "term").select("term", "doc_id", "pos", lo.alias("lo"), context.alias("context"))
            out = part if out is None else out.union(part)
        return self.scratch.save(out, f"postings-{self.made}")


def rarest(phrases: DataFrame, frequencies: DataFrame, lists: int) -> DataFrame:
    """(phrase, size, turn, term, offset): the ``lists`` rarest places of each phrase, turn 1 the rarest.

    A phrase with a term that never occurs cannot match and has no row.
    """
    places = phrases.select("phrase", "words").distinct().select("phrase", F.size("words").alias("size"), F.posexplode("words").alias("offset", "term"))
    order = Window.partitionBy("phrase").orderBy("n", "term", "offset")
    every = Window.partitionBy("phrase")
    places = places.join(frequencies, "term", "left").withColumn("found", F.count("n").over(every)).where("found = size")
    places = places.withColumn("turn", F.row_number().over(order)).where(F.col("turn") <= lists)
    return places.select("phrase", "size", "turn", "term", "offset")


def exact_matches(postings: DataFrame, lists: DataFrame) -> DataFrame:
    """(doc_id, phrase, start, size): every occurrence of every phrase."""
    shifted = postings.where(F.col("term") != END).join(lists, "term").withColumn("start", F.col("pos") - F.col("offset"))
    first = shifted.where("turn = 1 and start >= 0")
    other = shifted.where("turn > 1 and start >= 0").select("phrase", "doc_id", "start", "turn").distinct()
    needed = lists.groupBy("phrase").agg((F.count(F.lit(1)) - 1).alias("needed"))
    agreed = other.groupBy("phrase", "doc_id", "start").agg(F.count(F.lit(1)).alias("agreed"))
    keys = [first["phrase"] == agreed["phrase"], first["doc_id"].eqNullSafe(agreed["doc_id"]), first["start"] == agreed["start"]]
    both = first.join(agreed, keys, "left").select(first["*"], F.coalesce("agreed", F.lit(0)).alias("agreed")).join(needed, "phrase")
    there = F.concat_ws(" ", F.slice("context", F.col("start") - F.col("lo") + 1, F.col("size")))
    return both.where((F.col("agreed") == F.col("needed")) & (there == F.col("phrase"))).select("doc_id", "phrase", "start", "size").distinct()


def proximity_matches(docs: DataFrame, items: DataFrame, span: int = 20, terms: int = 5, scratch: Scratch | None = None) -> DataFrame:
    """(item_id, doc_id, pos): places where the ``terms`` rarest distinct terms of an item lie
    within ``span`` words of an occurrence of the rarest one, in any order.

    Items of fewer distinct terms need all they have; an item with a needed term that never
    occurs has no match.
    """
    scratch = scratch or Scratch(docs.sparkSession, "near-terms")
    index = PositionalIndex(docs, scratch)
    of = items.where("item_id is not null").select("item_id", F.explode(F.array_distinct(words_of(F.col("text")))).alias("term")).distinct()
    known = index.frequencies(of.select("term").distinct())
    order = Window.partitionBy("item_id").orderBy(F.col("n").asc_nulls_first(), "term")
    wanted = of.join(known, "term", "left").withColumn("turn", F.row_number().over(order)).where(F.col("turn") <= terms)
    wanted = scratch.save(wanted, "wanted")
    needed = wanted.groupBy("item_id").agg(F.count(F.lit(1)).alias("needed"), F.count("n").alias("found")).where("needed = found")
    lists = wanted.join(needed, "item_id").select("item_id", "term", "turn", "needed")
    postings = index.postings(lists.select("term", F.lit(False).alias("anchor")).distinct(), 0).where(F.col("term") != END)
    rows = postings.select("term", "doc_id", "pos").distinct().join(lists, "term")
    first = rows.where("turn = 1").select("item_id", "doc_id", F.col("pos").alias("at"), "needed", F.floor(F.col("pos") / span).alias("cell"))
    other = rows.where("turn > 1").select("item_id", "doc_id", "pos", "turn", F.explode(F.sequence(F.floor(F.col("pos") / span) - 1, F.floor(F.col("pos") / span) + 1)).alias("cell"))
    keys = (F.col("f.item_id") == F.col("o.item_id")) & F.col("f.doc_id").eqNullSafe(F.col("o.doc_id")) & (F.col("f.cell") == F.col("o.cell")) & (F.abs(F.col("f.at") - F.col("o.pos")) <= span)
    met = first.alias("f").join(other.alias("o"), keys, "left").groupBy("f.item_id", "f.doc_id", "f.at", "f.needed").agg(F.count_distinct("o.turn").alias("met"))
    return met.where("met = needed - 1").select("item_id", "doc_id", F.col("at").alias("pos"))


def contamination(docs: DataFrame, items: DataFrame, length: int = 10, scratch: Scratch | None = None) -> DataFrame:
    """Words of each document that lie in an occurrence of a window of an item.

    A window is ``length`` consecutive words of an item, or all its words if there are fewer.
    Null and empty texts have no words and no windows.  Items with a null item_id mark words
    but are not named.  Rows that share a doc_id, null included, are documents of their own unless
    their texts are equal too.  Empty tables give no matches or no rows.

    Returns doc_id, n_words, n_hit, n_items, items_sha256, contaminated.
    """
    own, scratch = scratch is None, scratch or Scratch(docs.sparkSession, "leaks")
    docs, key, named = keyed(docs.select("doc_id", "text"), scratch)
    index = PositionalIndex(docs.select(F.col(key).alias("doc_id"), "text"), scratch)
    phrases = scratch.save(phrases_of(items.select("item_id", "text"), length), "phrases")
    terms = phrases.select(F.explode("words").alias("term")).distinct()
    lists = scratch.save(rarest(phrases, index.frequencies(scratch.save(terms, "terms")), 2), "lists")
    needed = lists.groupBy("term").agg((F.min("turn") == 1).alias("anchor"))
    postings = index.postings(scratch.save(needed, "needed"), length - 1)
    found = scratch.save(exact_matches(postings, lists), "found")

    begun = Window.partitionBy("doc_id").orderBy("start", "stop").rowsBetween(Window.unboundedPreceding, -1)
    spans = found.groupBy("doc_id", "start").agg(F.max(F.col("start") + F.col("size")).alias("stop"))
    spans = spans.withColumn("from", F.greatest("start", F.coalesce(F.max("stop").over(begun), F.lit(0))))
    hits = spans.groupBy("doc_id").agg(F.sum(F.greatest(F.lit(0), F.col("stop") - F.col("from"))).alias("n_hit"))
    names = found.select("doc_id", "phrase").distinct().join(phrases.select("phrase", "item_id").where("item_id is not null"), "phrase")
    names = names.select("doc_id", F.col("item_id").cast("string").alias("name")).distinct()
    names = names.groupBy("doc_id").agg(F.sort_array(F.collect_list("name")).alias("names"))
    rows = postings.where(F.col("term") == END).select("doc_id", F.col("pos").cast("long").alias("n_words"))
    out = rows.join(hits.withColumnRenamed("doc_id", "h"), F.col("doc_id").eqNullSafe(F.col("h")), "left")
    out = out.join(names.withColumnRenamed("doc_id", "m"), F.col("doc_id").eqNullSafe(F.col("m")), "left")
    if named is not None:
        out = out.join(named.withColumnRenamed("doc_id", "of"), F.col("doc_id") == F.col(key)).drop("doc_id", key).withColumnRenamed("of", "doc_id")
    out = out.select(
        "doc_id",
        "n_words",
        F.coalesce("n_hit", F.lit(0)).cast("long").alias("n_hit"),
        F.coalesce(F.array_size("names"), F.lit(0)).cast("long").alias("n_items"),
        F.sha2(F.coalesce(F.array_join("names", ","), F.lit("")), 256).alias("items_sha256"),
        (F.coalesce("n_hit", F.lit(0)) > 0).alias("contaminated"),
    )
    return scratch.finish(out) if own else out
