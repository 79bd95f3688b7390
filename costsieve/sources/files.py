"""Sources and sinks: tables, other formats, and a generator of keys as a Python data source."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..functions import keys
from .shared import Staging, ship

FORMATS = {"csv": {"header": "true"}, "json": {}, "orc": {}, "parquet": {}}


def read(spark: SparkSession, path: str, kind: str, schema) -> DataFrame:
    """Read with a given schema; nothing is inferred."""
    return spark.read.schema(schema).options(**FORMATS[kind]).format(kind).load(path)


def write(df: DataFrame, path: str, kind: str, partition_by: list[str] | None = None) -> None:
    out = df.write.options(**FORMATS[kind]).format(kind)
    (out.partitionBy(*partition_by) if partition_by else out).save(path)


def round_trip(df: DataFrame, kind: str) -> DataFrame:
    path = f"{Staging(df.sparkSession, 'formats').path}/{kind}"
    write(df, path, kind)
    return read(df.sparkSession, path, kind, df.schema)


class _Range(InputPartition):
    def __init__(self, first: int, last: int):
        self.first, self.last = first, last


class _Reader(DataSourceReader):
    def __init__(self, options):
        self.n, self.parts = int(options.get("rows", 1000)), int(options.get("partitions", 4))

    def partitions(self):
        step = -(-self.n // self.parts)
        return [_Range(i, min(i + step, self.n)) for i in range(0, self.n, step)]

    def read(self, partition):
        import hashlib

        import pyarrow as pa

        for begin in range(partition.first, partition.last, 10_000):
            ids = range(begin, min(begin + 10_000, partition.last))
            made = ["okey" + hashlib.md5(str(i).encode()).hexdigest()[:16] for i in ids]
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(made)], ["id", "k"])


class KeyGenerator(DataSource):
    """Keys without visible traits: a 4-byte prefix and 64 bits as hex. Options: rows, partitions."""

    @classmethod
    def name(cls):
        return "sieve_keys"

    def schema(self):
        return "id bigint, k string"

    def reader(self, schema):
        return _Reader(self.options)


def generated(spark: SparkSession, rows: int, partitions: int = 4) -> DataFrame:
    ship(spark)
    spark.dataSource.register(KeyGenerator)
    return spark.read.format("sieve_keys").option("rows", rows).option("partitions", partitions).load()


def _customers(spark, d) -> DataFrame:
    return keys.table(spark, d, "customer").select("c_custkey", "c_name", "c_mktsegment")


_SQL = "SELECT c_custkey, c_name, c_mktsegment FROM customer"
QUERIES = (
    ("csv_round_trip", lambda spark, d: round_trip(_customers(spark, d), "csv"), _SQL),
    ("json_round_trip", lambda spark, d: round_trip(_customers(spark, d), "json"), _SQL),
    ("orc_round_trip", lambda spark, d: round_trip(_customers(spark, d), "orc"), _SQL),
    (
        "generated_keys",
        lambda spark, d: generated(spark, keys.table(spark, d, "orders").count()).select("id", "k"),
        "SELECT r AS id, 'okey' || substr(md5(r::VARCHAR), 1, 16) AS k FROM range(0, (SELECT count(*) FROM orders)) x(r)",
    ),
    ("text_lines", lambda spark, d: keys.table(spark, d, "pages").select("page_id", F.size(F.split("html", "\n")).alias("lines")), "SELECT page_id, len(string_split(html, chr(10)))::INT AS lines FROM pages"),
)
