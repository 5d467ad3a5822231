"""Intermediate tables in the shared folder, keys of documents, and taking documents out."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.scratch import Scratch as _Scratch
from ..sources.scratch import shared_folder

__all__ = ["Scratch", "free_name", "keyed", "shared_folder", "without"]


class Scratch(_Scratch):
    """Also knows what it holds, so that a method can leave nothing but its result."""

    def __init__(self, spark: SparkSession, label: str):
        super().__init__(spark, label)
        self.names: list[str] = []

    def save(self, df: DataFrame, name: str) -> DataFrame:
        self.names.append(name)
        return super().save(df, name)

    def only(self, *kept: str) -> None:
        """Delete every table but these."""
        for name in self.names:
            if name not in kept:
                self.drop(name)
        self.names = list(kept)

    def finish(self, df: DataFrame) -> DataFrame:
        """The result, written; all other tables are deleted."""
        out = self.save(df, "result")
        self.only("result")
        return out


def free_name(columns: Sequence[str], base: str) -> str:
    """A column name that is not taken, whatever the case."""
    taken = {c.lower() for c in columns}
    while base in taken:
        base += "_"
    return base


def keyed(docs: DataFrame, scratch: Scratch) -> tuple[DataFrame, str, DataFrame | None]:
    """``docs`` with a long column that tells documents apart, its name, and (name, doc_id) of every document
    where the two differ.

    It is doc_id where that is never null nor repeated.  Otherwise every (doc_id, text) has a number of
    its own; rows that repeat both share it.
    """
    key = free_name(docs.columns, "__key")
    ids = docs.groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.count(F.lit(1)).alias("n"))
    if ids.where("doc_id is null or n > 1").isEmpty():
        return docs.withColumn(key, F.col("doc_id").cast("long")), key, None
    text = F.coalesce(docs["text"].cast("string"), F.lit(""))
    prints = docs.select(docs["doc_id"].cast("long").alias("__of"), F.xxhash64(text).alias("__print")).distinct()
    numbers = scratch.save(prints.withColumn(key, F.monotonically_increasing_id()), "keys")
    same = docs["doc_id"].cast("long").eqNullSafe(F.col("__of")) & (F.xxhash64(text) == F.col("__print"))
    joined = docs.join(numbers.hint("shuffle_hash"), same).select(*[docs[c] for c in docs.columns], key)
    return joined, key, numbers.select(key, F.col("__of").alias("doc_id"))


def without(docs: DataFrame, gone: DataFrame, key: str) -> DataFrame:
    """``docs`` without the rows whose key is in ``gone`` (a column of that name), and without the key.

    The keys are hashed beside the documents, which are not sorted.
    """
    return docs.join(gone.select(key).distinct().hint("shuffle_hash"), key, "left_anti").drop(key)
