"""Sources and sinks: tables, text, round trips through other formats, a generated source, a summary store."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from rankspark import shipping


def load_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    shipping.ensure(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def scratch(spark: SparkSession) -> str:
    """A folder that all executors reach: the session's checkpoint folder, else its warehouse."""
    return (spark.conf.get("spark.checkpoint.dir", None) or spark.conf.get("spark.sql.warehouse.dir")).rstrip("/") + "/rankspark"


def require_numeric(df: DataFrame, column: str) -> None:
    kind = df.schema[column].dataType
    if not isinstance(kind, T.NumericType) or isinstance(kind, T.DecimalType):
        raise TypeError(f"{column} is {kind.simpleString()}; summaries take integers and floats, dates, timestamps and decimals go through engine.typed_quantiles")


def long_codec(kind: T.DataType) -> tuple[Callable, Callable]:
    """How a column of this type becomes a long of the same order, and back."""
    if isinstance(kind, T.IntegralType):
        return lambda c: c.cast("long"), lambda c: c.cast(kind)
    if isinstance(kind, T.DateType):
        return lambda c: F.unix_date(c).cast("long"), lambda c: F.date_from_unix_date(c.cast("int"))
    if isinstance(kind, (T.TimestampType, T.TimestampNTZType)):
        return lambda c: F.unix_micros(c.cast("timestamp")), lambda c: F.timestamp_micros(c).cast(kind)
    if isinstance(kind, T.DecimalType) and kind.precision <= 18:
        wide, one = T.DecimalType(38, kind.scale), 10**kind.scale
        return lambda c: (c.cast(wide) * F.lit(one)).cast("long"), lambda c: (c.cast("decimal(20,0)").cast(wide) / F.lit(one)).cast(kind)
    raise TypeError(f"{kind.simpleString()} has no order that a long carries")


def round_trip(df: DataFrame, kind: str, name: str) -> DataFrame:
    """Write in another format and read back with the same schema; text holds one integer a line."""
    spark, path = df.sparkSession, f"{scratch(df.sparkSession)}/{name}-{kind}-{uuid.uuid4().hex[:8]}"
    if kind == "text":
        df.select(F.col(df.columns[0]).cast("string")).write.mode("overwrite").text(path)
        return spark.read.text(path).select(F.col("value").cast("long").alias(df.columns[0]))
    df.write.mode("overwrite").format(kind).save(path)
    return spark.read.schema(df.schema).format(kind).load(path)


class ZipfSource(DataSource):
    """Integers in 1 .. range whose density falls as a power of the value, in any number of partitions: for tests at any size.

    Options: rows, range, exponent, partitions, seed."""

    @classmethod
    def name(cls) -> str:
        return "zipf"

    def schema(self) -> str:
        return "v long"

    def reader(self, schema) -> DataSourceReader:
        return ZipfReader(self.options)


class ZipfReader(DataSourceReader):
    def __init__(self, options):
        self.options = {k: float(options.get(k, d)) for k, d in (("rows", "1000000"), ("range", "1000000"), ("exponent", "0"), ("partitions", "8"), ("seed", "1"))}

    def partitions(self):
        return [InputPartition(i) for i in range(int(self.options["partitions"]))]

    def read(self, partition) -> Iterator:
        import numpy as np
        import pyarrow as pa

        o = self.options
        k, parts = partition.value, int(o["partitions"])
        left, rng, a = int(o["rows"]) * (k + 1) // parts - int(o["rows"]) * k // parts, np.random.default_rng([int(o["seed"]), k]), o["exponent"]
        while left:
            u = rng.random(min(left, 65_536))
            x = o["range"] ** u if a == 1 else (1 + u * (o["range"] ** (1 - a) - 1)) ** (1 / (1 - a))
            left -= len(u)
            yield pa.RecordBatch.from_arrays([pa.array(x.astype("int64"))], ["v"])
