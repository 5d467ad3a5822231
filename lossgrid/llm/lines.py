"""Line deduplication by an exact set-similarity join.

A line is the set of its words.  Words are ordered by rarity, so that two similar lines
must share a word among the first few of each; only these prefixes are joined.  Length and
position filters, and a parity bitmap of each line's words that bounds what two lines can
share, drop most pairs within the join; the rest is verified on whole sets.  Of two similar
lines the shorter one has a shared word among still fewer of its first words (its near heads):
near heads are joined with near heads, and with the far heads of longer lines.

Rarity: words are counted over all documents in ``CLASSES`` classes by hash; a word's level
is the logarithm of its class's count, which is never less than its own, and words of one
level are ordered by hash.  Any order shared by all lines gives the same result; rarity
makes the join small.

Lines with equal sets become one before anything is joined.  Prefix words of large classes
can stand in many lines: those lines are first compared with the ``CENTERS`` earliest that
have the word, and a line that matches one of these needs no other partner; what is left
of such words is joined by bands of length.  These lines keep their words beside them, so that
no text is read again for them.

Only DataFrame functions are used.  Levels are a constant array, and so is the filter that says which lines are
asked for; both reach the tasks as values of scalar subqueries, so that no plan, and no text of one that the driver
keeps, holds their elements.
"""

from __future__ import annotations

import math
from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .store import Scratch

CLASSES = 1 << 20
#: A class is hot from so many occurrences on, at least; more in a large corpus, as the square root of its words.
HOT, HOT_ROOT = 512, 9
#: Earliest lines with a hot word that all others with it are compared with first.
CENTERS = 4
#: Lines of more words have a second bitmap, as one of 64 bits says nothing about sets so large.
WIDE = 96
#: Bits of the filter that says which lines' words are asked for, at most.
FILTER = 1 << 26
#: Stands for a null doc_id, which comes first.
_NULL = -(1 << 63)
#: Bits of a word's hash below its level.
_BITS = 55


def _text(col: str = "text") -> Column:
    return F.coalesce(F.col(col).cast("string"), F.lit(""))


def _level(count: int | np.ndarray) -> np.ndarray:
    """Four steps for each doubling; 0 for a class without a word."""
    return np.where(np.asarray(count) > 0, np.minimum(1 + np.floor(4 * np.log2(np.maximum(count, 1))), 127), 0).astype(np.int8)


def _value(spark: SparkSession, values: np.ndarray) -> Column:
    """An array as the value of a scalar subquery."""
    whole = pa.ListArray.from_arrays(pa.array([0, len(values)], pa.int32()), pa.array(values))
    return spark.createDataFrame(pa.Table.from_arrays([whole], ["value"])).scalar()


def _texts(docs: DataFrame) -> DataFrame:
    """(d, print, text): d is doc_id with a number for null; in text all white space but line feeds is blanks."""
    text = _text()
    other = F.contains(text, F.lit("\t")) | F.contains(text, F.lit("\r")) | F.contains(text, F.lit("\x0b")) | F.contains(text, F.lit("\x0c"))
    blank = F.when(other, F.translate(text, "\t\r\x0b\x0c", "    ")).otherwise(text)
    return docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(_NULL)).alias("d"), F.xxhash64(text).alias("print"), blank.alias("text"))


def _lines(docs: DataFrame) -> DataFrame:
    """(d, lk, line): lk orders the lines of a document and, below that, tells texts of one doc_id apart."""
    rows = _texts(docs).select("d", "print", F.posexplode(F.split("text", "\n")).alias("no", "line"))  # texts are not handed on with each line
    return rows.select("d", F.shiftleft(F.col("no").cast("long"), 32).bitwiseOR(F.col("print").bitwiseAND(F.lit(0xFFFFFFFF))).alias("lk"), "line")


def _words() -> Column:
    """Distinct words of a line as hashes."""
    return F.array_remove(F.array_distinct(F.transform(F.split("line", " "), lambda w: F.xxhash64(w))), F.xxhash64(F.lit("")))


def _levels(texts: DataFrame, col: str) -> tuple[np.ndarray, int]:
    """The level of each class and the least level of a hot one."""
    words = texts.select(F.explode(F.split(F.replace(col, F.lit("\n"), F.lit(" ")), " ")).alias("word"))
    counts = words.groupBy(F.xxhash64("word").bitwiseAND(F.lit(CLASSES - 1)).cast("int").alias("class")).agg(F.count(F.lit(1)).alias("n"))
    level, total = np.zeros(CLASSES, np.int8), 0
    for batch in counts.toArrow().to_batches():
        n = batch.column(1).to_numpy()
        level[batch.column(0).to_numpy()], total = _level(n), total + int(n.sum())
    return level, int(_level(max(HOT, math.isqrt(total) // HOT_ROOT)))


def _leads(lines: DataFrame, percent: int, texts: DataFrame | None = None) -> DataFrame:
    """The earliest line of every set of words: d, lk, its size n, a parity bitmap of its words and, if it is wide, one of
    those of one kind (half), how many of its first words occur nowhere else (skip), how many are not hot, these
    included (cold), its other first words (head) and, if some are hot, the hashes of all its words.  Words are counted
    in ``texts``, where given, which are the same lines not yet cut."""
    level, hot = _levels(lines, "line") if texts is None else _levels(texts, "text")

    def ranked(w: Column) -> Column:
        at = F.coalesce(F.get("levels", w.bitwiseAND(F.lit(CLASSES - 1)).cast("int")).cast("long"), F.lit(0).cast("long"))  # never null: sorted as numbers
        return F.shiftleft(at, _BITS).bitwiseOR(w.bitwiseAND(F.lit((1 << _BITS) - 1)))

    def flipped(bits: Column, w: Column) -> Column:
        return bits.bitwiseXOR(F.call_function("shiftleft", F.lit(1).cast("long"), F.shiftright(w, 32).cast("int")))  # by its last six bits

    def half(bits: Column, w: Column) -> Column:
        kind = F.shiftright(w, 38).bitwiseAND(F.lit(1).cast("long"))
        return bits.bitwiseXOR(F.call_function("shiftleft", kind, F.shiftright(w, 32).cast("int")))

    def below(least: Column) -> Callable[[Column], Column]:
        return lambda w: w < least

    rows = lines.select("d", "lk", _words().alias("words"))
    # words are used more than once here and the levels once below: the optimizer puts the levels in there, so that they are in no row
    none = F.lit(0).cast("long")
    parity, halves = F.aggregate("words", none, flipped), F.when(F.size("words") > WIDE, F.aggregate("words", none, half)).otherwise(none)
    rows = rows.select("d", "lk", "words", F.size("words").alias("n"), parity.alias("parity"), halves.alias("half"), _value(lines.sparkSession, level).alias("levels"))
    rows = rows.select("d", "lk", "n", "parity", "half", "words", F.sort_array(F.transform("words", ranked)).alias("ranks"))
    size = F.col("n") - F.floor((F.col("n") * percent + 99) / 100).cast("int") + 1
    rows = rows.select("d", "lk", "n", "parity", "half", "words", F.xxhash64("ranks").alias("f1"), F.xxhash64(F.lit(1), "ranks").alias("f2"), F.slice("ranks", F.lit(1), size).alias("head"))
    skip, cold = (F.size(F.filter("head", below(F.lit(k << _BITS)))) for k in (int(_level(1)) + 1, hot))
    short = F.transform("head", lambda w: (w.bitwiseAND(F.lit(0xFFFFFFFF)) - F.lit(1 << 31)).cast("int"))
    rows = rows.select("d", "lk", "n", "parity", "half", "f1", "f2", skip.alias("skip"), cold.alias("cold"), short.alias("head"), "words")
    rows = rows.withColumn("words", F.when(F.col("cold") < F.size("head"), F.col("words")))
    rows = rows.withColumn("head", F.slice("head", F.col("skip") + 1, F.size("head")))
    first = F.min(F.struct("d", "lk", "n", "parity", "half", "skip", "cold", "head", "words")).alias("first")
    return rows.groupBy("f1", "f2").agg(first).select("first.*").where("n > 0")


def _needs(overlap: Column, percent: int, a: Column, b: Column) -> Column:
    return overlap * (100 + percent) >= (a + b) * percent


def _heads(leads: DataFrame) -> DataFrame:
    """One row for each first word: packed is the size, the place and, as its last bit, whether the line still
    looks for a partner, which all do at first."""
    rows = leads.select("d", "lk", "n", "parity", "half", "skip", "cold", F.posexplode("head").alias("pos", "word")).withColumn("pos", F.col("pos") + F.col("skip"))
    packed = F.shiftleft(F.col("n").cast("long"), 32).bitwiseOR(F.shiftleft(F.col("pos").cast("long"), 1)).bitwiseOR(F.lit(1))
    return rows.select("word", "d", "lk", "parity", "half", packed.alias("packed"), (F.col("pos") >= F.col("cold")).alias("hot"))


def _size(side: str = "") -> Column:
    return F.shiftright(F.col(f"{side}packed"), 32)


def _place(side: str = "") -> Column:
    return F.shiftright(F.col(f"{side}packed"), 1).bitwiseAND(F.lit(0x7FFFFFFF))


def _near(percent: int) -> Column:
    """Whether a head can be the first word that its line shares with one as long or longer."""
    return _needs(_size() - _place(), percent, _size(), _size())


def _apart() -> Column:
    """Words that one of x and y has and the other has not, at least."""
    bits, some = (F.col(f"x.{c}").bitwiseXOR(F.col(f"y.{c}")) for c in ("parity", "half"))
    both = (_size("x.") > WIDE) & (_size("y.") > WIDE)
    return F.when(both, F.bit_count(some) + F.bit_count(bits.bitwiseXOR(some))).otherwise(F.bit_count(bits))


def _before() -> Column:
    return (F.col("x.d") < F.col("y.d")) | ((F.col("x.d") == F.col("y.d")) & (F.col("x.lk") < F.col("y.lk")))


def _possible(percent: int) -> Column:
    """Whether sizes, places and bitmaps leave x and y a chance."""
    nx, ny = _size("x."), _size("y.")
    length = (nx * 100 >= ny * percent) & (ny * 100 >= nx * percent)
    place = _needs(F.least(nx - _place("x."), ny - _place("y.")), percent, nx, ny)
    return length & place & _needs(F.shiftright(nx + ny - _apart(), 1), percent, nx, ny)


def _met(x: DataFrame, y: DataFrame, on: list[str], condition: Column) -> DataFrame:
    for c in on:
        condition = (F.col(f"x.{c}") == F.col(f"y.{c}")) & condition
    return x.alias("x").join(y.hint("shuffle_hash").alias("y"), condition)


def _pairs(x: DataFrame, y: DataFrame, on: list[str], percent: int) -> DataFrame:
    """Pairs of which x is the earlier and y, the later, is open."""
    # with x in it, this is tested in the join, so that both sides of a self-join are one exchange
    opened = F.col("x.packed").bitwiseOR(F.lit(1)).bitwiseAND(F.col("y.packed")).bitwiseAND(F.lit(1)) == 1
    met = _met(x, y, on, opened & _possible(percent) & _before())
    return met.select(F.col("x.d").alias("xd"), F.col("x.lk").alias("xk"), F.col("y.d").alias("yd"), F.col("y.lk").alias("yk"), _apart().alias("miss"))


def _cold_pairs(heads: DataFrame, percent: int) -> DataFrame:
    """Pairs of lines that share a head, the earlier first.  x is the shorter and, of two as long, the earlier line;
    near heads are shuffled once for all three places where they stand."""
    near, far = heads.where(_near(percent)), heads.where(~_near(percent))
    nx, ny = _size("x."), _size("y.")
    shorter = (nx < ny) | ((nx == ny) & _before())
    ends = [F.when(_before(), F.col(f"{a}.{c}")).otherwise(F.col(f"{b}.{c}")).alias(f"{to}{c[-1]}") for to, a, b in (("x", "x", "y"), ("y", "y", "x")) for c in ("d", "lk")]
    met = [_met(near, near, ["word"], shorter & _possible(percent)), _met(far, near, ["word"], (ny < nx) & _possible(percent))]
    return met[0].select(*ends, _apart().alias("miss")).union(met[1].select(*ends, _apart().alias("miss")))


def _bands(heads: DataFrame, percent: int, near: bool) -> DataFrame:
    """Heads with a band of their line's length, or that one and the two beside it: lengths that can
    match are in the same or in neighbouring bands."""
    band = F.floor(F.log(F.shiftright(F.col("packed"), 32).cast("double")) / math.log(100 / min(percent, 99))).cast("int")
    return heads.withColumn("band", F.explode(F.array(band - 1, band, band + 1)) if near else band)


def _asked(lines: DataFrame, pairs: DataFrame, scratch: Scratch, name: str) -> DataFrame:
    """(d, lk, words) of the lines that ``pairs`` name, and of a few more: a bitmap of at most FILTER bits
    goes to the lines, so that others are neither cut into words nor shuffled.  A document that
    was read twice gives its lines twice."""
    wanted = pairs.select(F.col("xd").alias("d"), F.col("xk").alias("lk")).union(pairs.select("yd", "yk")).distinct()
    wanted = scratch.save(wanted, f"{name}-wanted")
    size = min(FILTER, max(1 << 15, 1 << math.ceil(math.log2(16 * max(1, wanted.count())))))
    place = F.xxhash64("d", "lk").bitwiseAND(F.lit(size - 1))
    marked = wanted.select((place + 1).alias("place")).groupBy(F.bitmap_bucket_number("place").alias("bucket")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("place")).alias("bits"))
    bits = np.zeros(size // 8, np.uint8)
    for r in marked.collect():  # a row of 4 KB for each 32768 bits
        lo = (r["bucket"] - 1) * 4096
        bits[lo : lo + 4096] = np.frombuffer(r["bits"], np.uint8)[: len(bits) - lo]
    eight = F.get(_value(lines.sparkSession, bits.view(np.int64)), F.shiftright(place, 6).cast("int"))
    hit = F.call_function("shiftright", eight, place.bitwiseAND(F.lit(63)).cast("int")).bitwiseAND(F.lit(1)) == 1
    return lines.where(hit).select("d", "lk", _words().alias("words"))


def _confirmed(sets: DataFrame, pairs: DataFrame, percent: int, scratch: Scratch, name: str) -> DataFrame:
    """(d, lk) of the later lines of those pairs whose words, in ``sets``, match; the likeliest partner of each
    line is looked at first, and all others only where that one does not match."""

    def matching(some: DataFrame, turn: str) -> DataFrame:
        both = some.join(sets.select(F.col("d").alias("xd"), F.col("lk").alias("xk"), F.col("words").alias("x")), ["xd", "xk"])
        both = both.join(sets.select(F.col("d").alias("yd"), F.col("lk").alias("yk"), F.col("words").alias("y")), ["yd", "yk"])
        alike = _needs(F.size(F.array_intersect("x", "y")), percent, F.size("x"), F.size("y"))
        return scratch.save(both.where(alike).select(F.col("yd").alias("d"), F.col("yk").alias("lk")).distinct(), f"{name}-{turn}")

    best = pairs.groupBy("yd", "yk").agg(F.min(F.struct("miss", "xd", "xk")).alias("best")).select("yd", "yk", "best.xd", "best.xk")
    found = matching(best, "best")
    known = found.select(F.col("d").alias("yd"), F.col("lk").alias("yk"))
    rest = pairs.join(known, ["yd", "yk"], "left_anti").join(best, ["yd", "yk", "xd", "xk"], "left_anti")
    return found.union(matching(rest, "rest"))


def _judged(docs: DataFrame, percent: int, scratch: Scratch) -> tuple[DataFrame, DataFrame]:
    """(d, lk) of the earliest line of every set of words, and of those of them that match an earlier one."""
    lines = _lines(docs)
    leads = scratch.save(_leads(lines, percent, _texts(docs)), "leads")

    hot = scratch.save(_heads(leads.where(F.col("cold") < F.col("skip") + F.size("head"))).where("hot").drop("hot"), "hot")
    first = Window.partitionBy("word").orderBy("d", "lk")
    centers = hot.withColumn("turn", F.row_number().over(first)).where(F.col("turn") <= CENTERS)
    pairs = scratch.save(_pairs(centers, hot, ["word"], percent).distinct(), "near-centers")
    sets = scratch.save(leads.where("words is not null").select("d", "lk", "words"), "centers-sets")
    matched = scratch.save(_confirmed(sets, pairs, percent, scratch, "centers"), "matched")
    if not matched.isEmpty():
        hot = hot.join(matched.withColumn("found", F.lit(True)), ["d", "lk"], "left").withColumn("packed", F.when(F.col("found"), F.col("packed").bitwiseAND(F.lit(-2))).otherwise(F.col("packed")))

    heads = _heads(leads).where("not hot").drop("hot")
    pairs = _cold_pairs(heads, percent)
    beside = _bands(hot.where(F.col("packed").bitwiseAND(F.lit(1)) == 1), percent, True)
    pairs = pairs.union(_pairs(_bands(hot, percent, False), beside, ["word", "band"], percent))
    pairs = pairs.distinct().join(matched.select(F.col("d").alias("yd"), F.col("lk").alias("yk")), ["yd", "yk"], "left_anti")
    pairs = scratch.save(pairs, "pairs")
    sets = scratch.save(_asked(lines, pairs, scratch, "all"), "all-sets")
    return leads.select("d", "lk"), matched.union(_confirmed(sets, pairs, percent, scratch, "all")).distinct()


def similar_lines(docs: DataFrame, percent: int = 80, scratch: Scratch | None = None) -> DataFrame:
    """Which lines repeat an earlier one: (doc_id, print, line_no, n_words, removed).

    Lines are the parts of a text between line feeds, numbered from 0; null counts as empty.  Two
    lines match if they share at least ``percent`` % of all their distinct words.  A line is removed
    if any earlier line matches it, earlier meaning by (doc_id, line_no); lines without words match
    nothing and stay.  print is a hash of the text, so that texts that share a doc_id are told
    apart; among lines of one number it decides which is earlier.  Rows that repeat both doc_id and
    text are one document read twice: their lines have the same answers.  A null doc_id comes first
    (as does -2**63, which is taken for null).  An empty table gives an empty result.
    """
    own, scratch = scratch is None, scratch or Scratch(docs.sparkSession, "lines")
    docs = docs.select("doc_id", "text")
    leads, matched = _judged(docs, percent, scratch)
    kept = scratch.save(leads.join(matched, ["d", "lk"], "left_anti"), "kept").withColumn("stays", F.lit(True))
    if own:
        scratch.only("kept")
    whole = docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(_NULL)).alias("d"), F.xxhash64(_text()).alias("print"), _text().alias("text"))
    whole = whole.select("d", "print", F.posexplode(F.split("text", "\n")).alias("line_no", "line"))
    lk = F.shiftleft(F.col("line_no").cast("long"), 32).bitwiseOR(F.col("print").bitwiseAND(F.lit(0xFFFFFFFF)))
    some = F.col("line").rlike("[^\\x20\\x09-\\x0D]")
    n_words = F.size(F.array_distinct(F.array_remove(F.split("line", "[\\x20\\x09-\\x0D]+"), ""))).cast("long")
    out = whole.select("d", "print", lk.alias("lk"), "line_no", n_words.alias("n_words"), some.alias("some")).join(kept, ["d", "lk"], "left")
    return out.select(F.nullif("d", F.lit(_NULL)).alias("doc_id"), "print", "line_no", "n_words", (F.col("some") & F.col("stays").isNull()).alias("removed"))


def removed_lines(docs: DataFrame, percent: int = 80, scratch: Scratch | None = None) -> DataFrame:
    """``line_report(similar_lines(docs, percent))``, made from whole documents: their lines are not joined
    one by one with those that stay."""
    own, scratch = scratch is None, scratch or Scratch(docs.sparkSession, "lines")
    docs = docs.select("doc_id", "text")
    leads, matched = _judged(docs, percent, scratch)
    both = leads.withColumn("gone", F.lit(False)).union(matched.withColumn("gone", F.lit(True)))
    low, no = F.col("lk").bitwiseAND(F.lit(0xFFFFFFFF)), F.shiftright("lk", 32).cast("int")
    both = both.select("d", low.alias("low"), no.alias("no"), "gone").repartition("d", "low")
    stay = both.groupBy("d", "low").agg(F.array_except(F.collect_list(F.when(~F.col("gone"), F.col("no"))), F.collect_list(F.when(F.col("gone"), F.col("no")))).alias("stay"))
    stay = scratch.save(stay, "stay")
    if own:
        scratch.only("stay")
    parts = F.split(_text(), "\n")
    some = F.filter(F.transform(parts, lambda line, k: F.when(line.rlike("[^\\x20\\x09-\\x0D]"), k).otherwise(-1)), lambda k: k >= 0)
    whole = docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(_NULL)).alias("d"), F.xxhash64(_text()).alias("print"), F.size(parts).cast("long").alias("n_lines"), some.alias("some"))
    whole = whole.groupBy("d", "print").agg(F.first("n_lines").alias("n_lines"), F.first("some").alias("some"))
    whole = whole.withColumn("low", F.col("print").bitwiseAND(F.lit(0xFFFFFFFF))).join(stay, ["d", "low"], "left")
    gone = F.when(F.col("stay").isNull(), F.col("some")).otherwise(F.array_except("some", "stay"))
    out = whole.select(F.nullif("d", F.lit(_NULL)).alias("doc_id"), "n_lines", gone.alias("removed_lines"))
    return out.select("doc_id", "n_lines", F.size("removed_lines").cast("long").alias("n_removed"), "removed_lines")


def line_report(lines: DataFrame) -> DataFrame:
    """Per document: doc_id, n_lines, n_removed, removed_lines (their numbers in order).

    Texts that share a doc_id have a row each; rows that repeat doc_id and text have one.
    """
    return _report(lines).drop("print")


def _report(lines: DataFrame) -> DataFrame:
    gone = F.sort_array(F.collect_set(F.when(F.col("removed"), F.col("line_no"))))
    out = lines.groupBy("doc_id", "print").agg((F.max("line_no") + 1).cast("long").alias("n_lines"), gone.alias("removed_lines"))
    return out.select("doc_id", "print", "n_lines", F.size("removed_lines").cast("long").alias("n_removed"), "removed_lines")


def drop_lines(docs: DataFrame, lines: DataFrame) -> DataFrame:
    """``docs`` with the removed lines taken out of text; other columns and rows as they are."""
    gone = _report(lines).where("n_removed > 0").select(F.col("doc_id").alias("__lines_of"), F.col("print").alias("__lines_in"), F.col("removed_lines").alias("__lines_gone"))
    same = docs["doc_id"].cast("long").eqNullSafe(F.col("__lines_of")) & (F.xxhash64(F.coalesce(docs["text"].cast("string"), F.lit(""))) == F.col("__lines_in"))
    joined = docs.join(gone.hint("shuffle_hash"), same, "left")
    kept = F.filter(F.split("text", "\n"), lambda line, k: ~F.array_contains(F.col("__lines_gone"), k))
    text = F.when(F.col("__lines_gone").isNull(), F.col("text")).otherwise(F.array_join(kept, "\n"))
    return joined.withColumn("text", text).select(*docs.columns)
