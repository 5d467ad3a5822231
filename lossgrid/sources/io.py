"""Tables in and out."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def load(spark: SparkSession, sf_dir: str, name: str, columns: Sequence[str] | None = None) -> DataFrame:
    """A Parquet table with only the columns asked for."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def read_any(spark: SparkSession, path: str, fmt: str, schema: str | None = None, **options: str) -> DataFrame:
    """csv, json, orc, parquet or text; text formats need a declared schema."""
    if fmt in ("csv", "json") and schema is None:
        raise ValueError(f"{fmt} is read with a declared schema")
    reader = spark.read.options(**options)
    return (reader.schema(schema) if schema else reader).format(fmt).load(path)


def write_any(df: DataFrame, path: str, fmt: str, **options: str) -> None:
    df.write.mode("overwrite").options(**options).format(fmt).save(path)


def write_partitioned(records: DataFrame, path: str, sort: Sequence[str] = ("row", "col"), spread: int = 1, most: int = 5_000_000) -> None:
    """Records (with part) in one folder for each part, sorted within files.

    ``spread`` salts every part over so many tasks by a hash of the whole record, so that neither a
    heavy part nor a heavy cell is one task's work.
    """
    salt = F.pmod(F.xxhash64(*records.columns), F.lit(spread))
    dealt = records.withColumn("__salt", salt).repartition("part", "__salt").drop("__salt").sortWithinPartitions("part", *sort)
    dealt.write.mode("overwrite").option("maxRecordsPerFile", most).partitionBy("part").parquet(path)


def write_bucketed(df: DataFrame, table: str, key: str, buckets: int) -> None:
    """A table bucketed and sorted by ``key``: joins on it need no shuffle."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).format("parquet").saveAsTable(table)


def parts_of(cells: DataFrame, box: tuple[int, int, int, int]) -> list[int]:
    """Parts that a box of rows and columns (r0, r1, c0, c1, inclusive) touches; at most g of them."""
    r0, r1, c0, c1 = box
    hit = cells.where(F.col("row").between(r0, r1) & F.col("col").between(c0, c1)).select("part").distinct()
    return sorted(r[0] for r in hit.collect())


def read_parts(spark: SparkSession, path: str, cells: DataFrame, box: tuple[int, int, int, int]) -> DataFrame:
    """Records in a box, from the folders of the parts it touches only."""
    r0, r1, c0, c1 = box
    return spark.read.parquet(path).where(F.col("part").isin(parts_of(cells, box)) & F.col("row").between(r0, r1) & F.col("col").between(c0, c1))


def sample_exact(df: DataFrame, k: int, key: Column, seed: int = 0) -> DataFrame:
    """The k rows with the smallest hashes; each task keeps k at most."""
    h = F.pmod((key.cast("long") + F.lit(seed)) * F.lit(2654435761), F.lit(1 << 32))
    return df.withColumn("__h", h).orderBy("__h", key).limit(k).drop("__h")


def save_model(model, spark: SparkSession, path: str) -> None:
    model.table(spark).write.mode("overwrite").parquet(path)


def save_trace(trace: list[dict], spark: SparkSession, path: str) -> None:
    spark.createDataFrame(trace).write.mode("overwrite").parquet(path)


def text_attributes(df: DataFrame, text: str = "text") -> DataFrame:
    """Numbers of a text column: characters, words, sentences, share of letters."""
    t = F.coalesce(F.col(text), F.lit(""))
    letters = F.length(F.regexp_replace(t, "[^A-Za-z]", ""))
    return df.withColumns(
        {
            "n_chars_": F.length(t),
            "n_words": F.when(F.length(F.trim(t)) > 0, F.size(F.split(F.trim(t), "\\s+"))).otherwise(0),
            "n_sentences": F.regexp_count(t, F.lit("[.!?]+")),
            "letter_share": F.when(F.length(t) > 0, letters / F.length(t)).otherwise(F.lit(0.0)),
        }
    )
