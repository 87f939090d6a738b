"""Readers for the given tables, and the splits and derived columns of the workloads."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


def read_table(spark: SparkSession, folder: str, name: str, fmt: str = "parquet", schema: T.StructType | None = None) -> DataFrame:
    """A table of a folder; text formats need a declared schema."""
    if fmt in ("csv", "json") and schema is None:
        raise ValueError(f"{fmt} needs a declared schema")
    reader = spark.read if schema is None else spark.read.schema(schema)
    if fmt == "csv":
        reader = reader.option("header", True)
    return reader.format(fmt).load(f"{folder}/{name}.{fmt}")


def split_number() -> Column:
    return (F.col("l_orderkey") * 31 + F.col("l_linenumber")) % 200


def whole_parts(lineitem: DataFrame, percents: list[int]) -> list[DataFrame]:
    """The base and deltas of so many percent of it, together the whole table; rows without a split number are in the base."""
    at = F.coalesce(split_number(), F.lit(0)) * (100 + sum(percents))
    ends = [200 * (100 + sum(percents[:i])) for i in range(len(percents))]
    return [lineitem.where((at >= lo if lo else F.lit(True)) & (at < hi if hi else F.lit(True))) for lo, hi in zip([None, *ends], [*ends, None], strict=True)]


def with_receipt_date(lineitem: DataFrame) -> DataFrame:
    days = 1 + (F.col("l_orderkey") * 7 + F.col("l_linenumber")) % 30
    return lineitem.withColumn("receiptdate", F.col("l_shipdate") + F.make_dt_interval(days.cast("int")))


def replicated(lineitem: DataFrame, copies: int) -> DataFrame:
    """The table so many times over, order keys shifted, for larger sizes."""
    span = lineitem.agg(F.max("l_orderkey")).first()[0] + 1
    return lineitem.withColumn("copy", F.explode(F.sequence(F.lit(0), F.lit(copies - 1)))).withColumn("l_orderkey", F.col("l_orderkey") + F.col("copy") * span).drop("copy")


def star_fact(spark: SparkSession, folder: str) -> DataFrame:
    """Line items with customer segment and region.  The smallest tables have a fixed number of rows; Spark picks the other joins."""
    t = lambda name: read_table(spark, folder, name)
    places = t("nation").join(F.broadcast(t("region")), F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", "r_name")
    customers = t("customer").join(F.broadcast(places), F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", "c_mktsegment", "r_name")
    orders = t("orders").select("o_orderkey", "o_custkey").join(customers, F.col("o_custkey") == F.col("c_custkey")).select("o_orderkey", "c_mktsegment", "r_name")
    return t("lineitem").join(orders, F.col("l_orderkey") == F.col("o_orderkey"))


def read_events_stream(spark: SparkSession, folder: str, files_per_trigger: int = 1) -> DataFrame:
    """Event files as a stream, with the declared schema of ``events``."""
    schema = T.StructType([T.StructField("event_id", T.LongType()), T.StructField("ts", T.TimestampNTZType()), T.StructField("user_id", T.LongType()), T.StructField("event_type", T.StringType()), T.StructField("value", T.DoubleType()), T.StructField("props", T.StringType())])
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(folder)


def user_function(df: DataFrame, name: str, column: str, fn, kind: str) -> DataFrame:
    """A derived column by a vectorised Python function over Arrow batches."""
    return df.withColumn(name, F.pandas_udf(fn, kind)(F.col(column)))
