"""Readers and writers."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def load(spark: SparkSession, folder: str, name: str, columns: list[str] | None = None, where: Column | str | None = None) -> DataFrame:
    """One parquet table; the columns and the predicate reach the scan."""
    df = spark.read.parquet(f"{folder}/{name}.parquet")
    if where is not None:
        df = df.where(where)
    return df.select(*columns) if columns else df


def load_as(spark: SparkSession, path: str, kind: str = "parquet", **options) -> DataFrame:
    """json, csv, orc or parquet files."""
    return spark.read.format(kind).options(**options).load(path)


def client_bucket(client: Column, buckets: int) -> Column:
    """Partition number of a client: the lake's layout key."""
    return F.pmod(F.xxhash64(client), F.lit(buckets)).cast("int")


def save(df: DataFrame, path: str, partition_by: list[str] | None = None, kind: str = "parquet", mode: str = "overwrite") -> None:
    writer = df.write.format(kind).mode(mode)
    (writer.partitionBy(*partition_by) if partition_by else writer).save(path)


def save_client_lake(interactions: DataFrame, path: str, buckets: int = 64) -> None:
    """Interactions by client bucket, sorted by client inside each file, so that a schedule prunes files and row groups."""
    placed = interactions.withColumn("client_bucket", client_bucket(F.col("client_id"), buckets))
    placed.repartition(buckets, "client_bucket").sortWithinPartitions("client_bucket", "client_id").write.mode("overwrite").partitionBy("client_bucket").parquet(path)


def read_scheduled(spark: SparkSession, path: str, schedule: DataFrame, buckets: int = 64) -> DataFrame:
    """Only the scheduled clients' rows of a client lake: buckets are pruned by the join's keys at run time."""
    wanted = schedule.select("client_id").distinct().withColumn("client_bucket", client_bucket(F.col("client_id"), buckets))
    return spark.read.parquet(path).join(wanted, ["client_bucket", "client_id"], "left_semi")


def save_bucketed(df: DataFrame, table: str, key: str = "client_id", buckets: int = 16) -> None:
    """A bucketed and sorted table: later joins and packings on ``key`` need no exchange."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(table)


def register_client_shards(spark: SparkSession) -> None:
    """A Python data source ``client_shards``: one input partition per client bucket of a client lake.

    Option ``path`` names the lake, ``buckets`` the number of buckets; an equality or
    IN filter on client_bucket is pushed into the list of partitions.
    """
    from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, In, InputPartition

    class Shards(DataSourceReader):
        def __init__(self, options):
            self.path, self.chosen = options["path"], range(int(options.get("buckets", 64)))

        def pushFilters(self, filters):
            for f in filters:
                if isinstance(f, EqualTo) and f.attribute == ("client_bucket",):
                    self.chosen = [x for x in self.chosen if x == f.value]
                elif isinstance(f, In) and f.attribute == ("client_bucket",):
                    self.chosen = [x for x in self.chosen if x in f.value]
                else:
                    yield f

        def partitions(self):
            return [InputPartition(x) for x in self.chosen]

        def read(self, partition):
            import pyarrow as pa
            import pyarrow.dataset as ds

            folder = f"{self.path.removeprefix('file:')}/client_bucket={partition.value}"
            try:
                data = ds.dataset(folder, format="parquet").to_table(columns=["client_id", "item_id", "label"])
            except FileNotFoundError:
                return
            for batch in data.to_batches():
                named = batch.cast(pa.schema([("client_id", pa.int64()), ("item_id", pa.int64()), ("label", pa.int32())]))
                yield pa.RecordBatch.from_arrays([pa.array([partition.value] * len(named), pa.int32()), *named.columns], ["client_bucket", "client_id", "item_id", "label"])

    class ClientShards(DataSource):
        @classmethod
        def name(cls):
            return "client_shards"

        def schema(self):
            return "client_bucket int, client_id long, item_id long, label int"

        def reader(self, schema):
            return Shards(self.options)

    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(ClientShards)
