"""Relations from files and tables, and sinks."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Fixed schemas, so that nothing is inferred from the data.
EDGES = T.StructType([T.StructField("s", T.LongType()), T.StructField("t", T.LongType())])
CAST = T.StructType([T.StructField("p", T.LongType()), T.StructField("m", T.LongType())])


def read_edge_list(spark: SparkSession, path: str, sep: str = "\t", schema: T.StructType = EDGES) -> DataFrame:
    """Text with an edge on each line; lines that begin with # are comments. Lines that do not parse are dropped."""
    return spark.read.csv(path, sep=sep, comment="#", schema=schema, mode="DROPMALFORMED").dropna().distinct()


def from_csv(spark: SparkSession, path: str, schema: T.StructType, header: bool = True) -> DataFrame:
    return spark.read.csv(path, schema=schema, header=header)


def from_json(spark: SparkSession, path: str, schema: T.StructType) -> DataFrame:
    return spark.read.json(path, schema=schema)


def from_orc(spark: SparkSession, path: str, columns: list[str]) -> DataFrame:
    return spark.read.orc(path).select(*columns)


def from_parquet(spark: SparkSession, path: str, columns: list[str]) -> DataFrame:
    return spark.read.parquet(path).select(*columns)


def from_table(spark: SparkSession, name: str, columns: list[str]) -> DataFrame:
    return spark.table(name).select(*columns)


def save_bucketed(df: DataFrame, table: str, columns: list[str], buckets: int = 64) -> DataFrame:
    """A managed table bucketed and sorted by its join columns: later joins on them need no shuffle."""
    df.write.bucketBy(buckets, *columns).sortBy(*columns).mode("overwrite").saveAsTable(table)
    return df.sparkSession.table(table)


def save_partitioned(df: DataFrame, path: str, by: str) -> None:
    df.repartition(by).write.partitionBy(by).mode("overwrite").parquet(path)


def both_orientations(edges: DataFrame, name: str, buckets: int = 64) -> tuple[DataFrame, DataFrame]:
    """An edge relation stored twice, bucketed by source and by target, so that either end extends without a shuffle."""
    return save_bucketed(edges, f"{name}_by_s", ["s"], buckets), save_bucketed(edges, f"{name}_by_t", ["t"], buckets)


def drain(df: DataFrame) -> None:
    """Compute every row and store none: the sink for timing evaluation."""
    df.write.format("noop").mode("overwrite").save()


def encode_values(df: DataFrame, columns: list[str], work: str) -> tuple[DataFrame, DataFrame]:
    """df with the columns as dense numbers, and the dictionary (value, id) in the order of values.

    Values are range-partitioned and numbered within a partition; the partitions' sizes give the offsets. The
    numbered values are written to work first, so that a lost task cannot number them differently.
    """
    values = None
    for c in columns:
        one = df.select(F.col(c).cast("string").alias("value")).dropna()
        values = one if values is None else values.unionByName(one)
    spark = df.sparkSession
    n = int(spark.conf.get("spark.sql.shuffle.partitions"))
    ranged = values.distinct().repartitionByRange(n, "value").sortWithinPartitions("value")

    def number(batches):
        import pyarrow as pa
        from pyspark import TaskContext

        part, at = TaskContext.get().partitionId(), 0
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([part] * b.num_rows, pa.int32()), pa.array(range(at, at + b.num_rows), pa.int64())], ["value", "part", "rank"])
            at += b.num_rows

    ranged.mapInArrow(number, "value string, part int, rank long").write.mode("overwrite").parquet(work)
    numbered = spark.read.parquet(work)
    sizes = sorted(numbered.groupBy("part").agg(F.count(F.lit(1)).alias("n")).collect())  # a row for each partition
    offset, rows = 0, []
    for part, size in sizes:
        rows.append((part, offset))
        offset += size
    offsets = spark.createDataFrame(rows, "part int, offset long")
    dictionary = numbered.join(F.broadcast(offsets), "part").select("value", (F.col("rank") + F.col("offset")).alias("id"))
    out = df
    for c in columns:
        out = out.join(dictionary.select(F.col("value").alias(f"__{c}"), F.col("id").alias(f"__id_{c}")), F.col(c).cast("string") == F.col(f"__{c}"), "left").drop(f"__{c}")
    return out.select(*[F.col(f"__id_{c}").alias(c) if c in columns else F.col(c) for c in df.columns]), dictionary
