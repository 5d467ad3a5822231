"""Exact deduplication against a persistent digest index.

The index is a table of one row per distinct normalised text, bucketed and sorted by
digest.  New data is digested, reduced to one row per digest (combined before the
shuffle), kept where a sort-merge anti-join finds no such digest in the index, and
appended.  Only DataFrame functions are used.
"""

from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.utils import AnalysisException

from .store import Scratch, free_name, shared_folder

#: Deleted before texts are compared (code points 20, 09-0D).
SPACES = " \t\n\x0b\x0c\r"
#: A digest is frequent if it has more than one in so many rows: under HOT of them can exist.
HOT = 2000


def normalised(text: Column) -> Column:
    out = F.coalesce(text.cast("string"), F.lit(""))
    for c in SPACES:
        out = F.replace(out, F.lit(c), F.lit(""))
    return out


def digest(text: Column) -> Column:
    return F.sha2(normalised(text).cast("binary"), 256)


def digests(docs: DataFrame) -> DataFrame:
    """doc_id, size (code points of the original text; null has 0) and text_sha256 of each row."""
    size = F.coalesce(F.length("text"), F.lit(0)).cast("long")
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), size.alias("size"), digest(F.col("text")).alias("text_sha256"))


def leaders(rows: DataFrame) -> DataFrame:
    """Of each digest the longest original, then the smallest doc_id; a null doc_id comes last."""
    best = F.max(F.struct("size", F.col("doc_id").isNotNull().alias("named"), F.bitwise_not("doc_id").alias("flipped"))).alias("best")
    out = rows.groupBy("text_sha256").agg(best, F.count(F.lit(1)).alias("group_size"))
    return out.select("text_sha256", F.bitwise_not("best.flipped").alias("keep_id"), F.col("best.size").alias("keep_size"), "group_size")


class DigestIndex:
    """A bucketed and sorted table of digests that outlives the session's data.

    ``name`` is a table of the session's catalog; with ``folder`` its files lie there, so that
    a later session can attach them again under the same name.
    """

    SCHEMA = "text_sha256 string, keep_id long, keep_size long, group_size long"

    def __init__(self, spark: SparkSession, name: str | None = None, folder: str | None = None, buckets: int | None = None):
        self.spark = spark
        self.name = name or f"digest_index_{uuid.uuid4().hex}"
        self.folder = folder or f"{shared_folder(spark)}/{self.name}"
        self.buckets = buckets or int(spark.conf.get("spark.sql.shuffle.partitions"))
        if not spark.catalog.tableExists(self.name):
            spark.sql(
                f"CREATE TABLE {self.name} ({self.SCHEMA}) USING parquet LOCATION '{self.folder}' "
                f"CLUSTERED BY (text_sha256) SORTED BY (text_sha256) INTO {self.buckets} BUCKETS"
            )

    def table(self) -> DataFrame:
        return self.spark.table(self.name)

    def absorb(self, rows: DataFrame) -> None:
        """Append the leaders of digests that the index does not have."""
        new = leaders(rows).hint("merge").join(self.table(), "text_sha256", "left_anti")
        new = new.select("text_sha256", "keep_id", "keep_size", "group_size")
        new.write.insertInto(self.name)
        self.spark.catalog.refreshTable(self.name)

    def drop(self) -> None:
        """The table and its files."""
        try:
            self.spark.sql(f"DROP TABLE IF EXISTS {self.name}")
        except AnalysisException:  # already gone with its session
            pass
        path = self.spark._jvm.org.apache.hadoop.fs.Path(self.folder)
        path.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(path, True)


def _placed(rows: DataFrame, index: DataFrame, scratch: Scratch) -> DataFrame:
    """rows with their index row.  Frequent digests, of which fewer than HOT can exist, are joined
    by broadcast so that no task gets a group of copies; the others meet the sorted index."""
    total = rows.count()
    counts = rows.groupBy("text_sha256").agg(F.count(F.lit(1)).alias("n"))
    hot = scratch.save(counts.where((F.col("n") * HOT > F.lit(total)) & (F.col("n") > 100)).select("text_sha256"), "hot")
    few = F.broadcast(hot)
    often = rows.join(F.broadcast(index.join(few, "text_sha256", "left_semi")), "text_sha256")
    seldom = rows.join(few, "text_sha256", "left_anti").hint("merge").join(index, "text_sha256")
    return often.unionByName(seldom)


def exact_duplicates(docs: DataFrame, index: DigestIndex | None = None) -> DataFrame:
    """The decision on every row of ``docs`` (doc_id, text), dropped rows too.

    Texts are equal when they are once every space, tab, line feed, vertical tab, form feed and
    carriage return is deleted; null counts as empty, and empty texts are equal to each other.
    Of equal texts the longest original stays, then the smallest doc_id; null doc_ids come last.
    With an index that already has a text, the row named there stays and none of ``docs``, and
    group_size counts it and the rows of ``docs``.  Without one, an index is made and dropped again.
    Rows that repeat both doc_id and size of the row that stays: one of them is kept.
    An empty table gives an empty result; other columns are ignored.

    Returns doc_id, keep_id, group_size, kept, text_sha256.
    """
    spark = docs.sparkSession
    scratch = Scratch(spark, "exact")
    rows = scratch.save(digests(docs), "digests")
    fresh = index is None
    index = index or DigestIndex(spark)
    known = None if fresh else scratch.save(index.table().select("text_sha256"), "known")
    index.absorb(rows)
    out = _placed(rows, index.table(), scratch)
    if known is not None:  # of a text that the index had, its row stands for one document
        here = rows.groupBy("text_sha256").agg(F.count(F.lit(1)).alias("here")).join(known.withColumn("had", F.lit(1)), "text_sha256", "left")
        here = here.select("text_sha256", (F.col("here") + F.coalesce("had", F.lit(0))).cast("long").alias("in_all"))
        out = out.join(here, "text_sha256").withColumn("group_size", F.col("in_all")).drop("in_all")
    same = out.where(F.col("doc_id").eqNullSafe(F.col("keep_id")) & (F.col("size") == F.col("keep_size")))
    rest = out.where(~(F.col("doc_id").eqNullSafe(F.col("keep_id")) & (F.col("size") == F.col("keep_size"))))
    cols = ["doc_id", "keep_id", "group_size", "text_sha256"]
    same = same.groupBy(*cols).agg(F.count(F.lit(1)).cast("int").alias("copies"))
    same = same.select(*cols, F.explode(F.sequence(F.lit(1), F.col("copies"))).alias("copy"))
    same = same.select(*cols, (F.col("copy") == 1).alias("kept"))
    if known is not None:
        old = known.withColumn("old", F.lit(True))
        same = same.join(old, "text_sha256", "left").select(*cols, (F.col("kept") & F.col("old").isNull()).alias("kept"))
    out = same.unionByName(rest.select(*cols, F.lit(False).alias("kept")))
    out = scratch.finish(out.select("doc_id", "keep_id", "group_size", "kept", "text_sha256"))
    if fresh:
        index.drop()
    return out


def keep_first(docs: DataFrame) -> DataFrame:
    """Rows of ``docs``, all columns, without exact copies: see :func:`exact_duplicates`.

    Of rows that repeat the doc_id and text of a row that stays, one stays.
    """
    found = exact_duplicates(docs)
    of, sha, size, best = (free_name(docs.columns, c) for c in ("__id", "__sha", "__size", "__best"))
    rows = found.groupBy("doc_id", "text_sha256").agg(F.count(F.lit(1)).alias("n"), F.max("kept").alias("kept"))
    gone = rows.where("not kept").select(F.col("doc_id").alias(of), F.col("text_sha256").alias(sha))
    again = rows.where("kept and n > 1").select(F.col("doc_id").alias(of), F.col("text_sha256").alias(sha))
    same = docs["doc_id"].cast("long").eqNullSafe(F.col(of)) & (digest(docs["text"]) == F.col(sha))
    kept = docs.join(gone.hint("shuffle_hash"), same, "left_anti")
    if again.isEmpty():
        return kept
    same = kept["doc_id"].cast("long").eqNullSafe(F.col(of)) & (digest(kept["text"]) == F.col(sha))
    once = kept.join(again.hint("shuffle_hash"), same, "left_anti")
    more = kept.join(again.hint("shuffle_hash"), same, "left_semi")
    more = more.withColumns({sha: digest(F.col("text")), size: F.coalesce(F.length("text"), F.lit(0))})
    columns = docs.columns
    top = more.groupBy("doc_id", sha).agg(F.max(F.struct(F.col(size), *[F.struct(F.col(c)).alias(f"v{k}") for k, c in enumerate(columns)])).alias(best))
    return once.unionByName(top.select(*[F.col(f"{best}.v{k}.{c}").alias(c) for k, c in enumerate(columns)]))
