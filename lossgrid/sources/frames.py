"""Small tables to and from the driver as Arrow."""

from __future__ import annotations

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession


def to_spark(spark: SparkSession, pdf: pd.DataFrame, schema: pa.Schema | None = None) -> DataFrame:
    return spark.createDataFrame(pa.Table.from_pandas(pdf, schema=schema, preserve_index=False))


def to_pandas(df: DataFrame) -> pd.DataFrame:
    return df.toArrow().to_pandas()
