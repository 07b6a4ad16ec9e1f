"""Readers: the given tables, common file formats, streams of files, generated streams."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, DataSourceStreamReader, InputPartition
from pyspark.sql.types import StructType


def table(spark: SparkSession, folder: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{folder}/{name}.parquet")


def read(spark: SparkSession, path: str, kind: str = "parquet", schema: StructType | str | None = None, **options: str) -> DataFrame:
    """parquet, orc, json, csv or text; text formats want a schema."""
    reader = spark.read.options(**options)
    return (reader.schema(schema) if schema else reader).format(kind).load(path)


def stream(spark: SparkSession, path: str, schema: StructType | str, kind: str = "parquet", files_per_trigger: int | None = None) -> DataFrame:
    """A folder of files as a stream."""
    reader = spark.readStream.schema(schema).format(kind)
    if files_per_trigger:
        reader = reader.option("maxFilesPerTrigger", files_per_trigger)
    return reader.load(path)


def rate(spark: SparkSession, rows_per_batch: int = 1000, micro_batch: bool = True) -> DataFrame:
    """Spark's own generators."""
    if micro_batch:
        return spark.readStream.format("rate-micro-batch").option("rowsPerBatch", rows_per_batch).load()
    return spark.readStream.format("rate").option("rowsPerSecond", rows_per_batch).load()


def kafka(spark: SparkSession, servers: str, topic: str, schema: str) -> DataFrame:
    """Stream tuples from Kafka messages in JSON; the connector must be on the class path."""
    raw = spark.readStream.format("kafka").option("kafka.bootstrap.servers", servers).option("subscribe", topic).load()
    return raw.select(F.from_json(F.col("value").cast("string"), schema).alias("t"), F.col("offset").alias("seq"), F.col("timestamp").alias("ts")).select("t.*", "seq", "ts")


# -- generated values, reproducible from an integer hash ------------------------------------

# The multiplier and increment of a common linear congruential generator, modulo 2**31.
MULTIPLIER, INCREMENT, MODULUS = 1103515245, 12345, 1 << 31


def hashed(id_: str, salt: int) -> str:
    """SQL of a pseudo-random number below 2**31; the same in Spark and DuckDB."""
    once = f"(({id_} * 31 + {salt}) * {MULTIPLIER} + {INCREMENT}) % {MODULUS}"
    return f"(({once}) * {MULTIPLIER} + {INCREMENT}) % {MODULUS}"


def distribution_sql(kind: str, id_: str = "id") -> str:
    """SQL of a value: uniform, narrow, normal (two modes), zipf (rank-size), geometric."""
    integer = lambda x: f"CAST(floor({x}) AS BIGINT)"
    if kind == "uniform":
        return f"({hashed(id_, 1)})"
    if kind == "narrow":
        return f"(1000000 + ({hashed(id_, 1)}) % 4096)"
    if kind == "normal":
        parts = " + ".join(f"({hashed(id_, k)}) % 1000000" for k in range(1, 13))
        return f"(({parts}) + CASE WHEN {id_} % 3 = 0 THEN 40000000 ELSE 0 END)"
    if kind == "zipf":
        return integer(f"1000000000.0 / (1 + ({hashed(id_, 1)}) % 100000)")
    if kind == "geometric":
        return integer(f"4294967296.0 / power(16, {id_} % 8)")
    raise ValueError(kind)


def generated(spark: SparkSession, n: int, kind: str) -> DataFrame:
    """(key, value) of a seeded distribution."""
    return spark.range(n).selectExpr("id as key", f"cast({distribution_sql(kind)} as bigint) as value")


def generated_on(rows: DataFrame, key: str, kind: str) -> DataFrame:
    """(key, value) of a seeded distribution over a table's own keys, which are whole numbers."""
    return rows.selectExpr(f"{key} as key", f"cast({distribution_sql(kind, key)} as bigint) as value")


def two_streams(spark: SparkSession, n: int, kind: str) -> DataFrame:
    """(side, key, value, rank, seen_s, seen_r, seq): sides alternate."""
    rows = spark.range(n).selectExpr("id", f"cast({distribution_sql(kind)} as bigint) as value")
    return rows.selectExpr("if(id % 2 = 0, 'S', 'R') as side", "id as key", "value", "id div 2 + 1 as rank", "(id + 2) div 2 as seen_s", "(id + 1) div 2 as seen_r", "id + 1 as seq")


class _Part(InputPartition):
    def __init__(self, first: int, last: int):
        self.first, self.last = first, last


def _value(i: int, salt: int = 1) -> int:
    once = ((i * 31 + salt) * MULTIPLIER + INCREMENT) % MODULUS
    return (once * MULTIPLIER + INCREMENT) % MODULUS


class _Reader(DataSourceReader):
    def __init__(self, n: int, parts: int):
        self.n, self.parts = n, parts

    def partitions(self) -> list[InputPartition]:
        return [_Part(self.n * k // self.parts, self.n * (k + 1) // self.parts) for k in range(self.parts)]

    def read(self, partition: _Part) -> Iterator[tuple]:
        for i in range(partition.first, partition.last):
            yield i, "SR"[i % 2], i, _value(i)


class _StreamReader(DataSourceStreamReader):
    def __init__(self, n: int, step: int):
        self.n, self.step, self.at = n, step, 0

    def initialOffset(self) -> dict:  # noqa: N802
        return {"at": 0}

    def latestOffset(self) -> dict:  # noqa: N802
        self.at = min(self.n, self.at + self.step)
        return {"at": self.at}

    def partitions(self, start: dict, end: dict) -> list[InputPartition]:
        return [_Part(start["at"], end["at"])]

    def read(self, partition: _Part) -> Iterator[tuple]:
        return _Reader(self.n, 1).read(partition)

    def commit(self, end: dict) -> None:
        pass


class StreamTuples(DataSource):
    """``spark.read.format("stream_tuples")``: seeded uniform tuples, batch or stream."""

    @classmethod
    def name(cls) -> str:
        return "stream_tuples"

    def schema(self) -> str:
        return "seq bigint, side string, key bigint, value bigint"

    def reader(self, schema: StructType) -> DataSourceReader:
        return _Reader(int(self.options.get("rows", 1000)), int(self.options.get("parts", 2)))

    def streamReader(self, schema: StructType) -> DataSourceStreamReader:  # noqa: N802
        return _StreamReader(int(self.options.get("rows", 1000)), int(self.options.get("step", 250)))


def register(spark: SparkSession) -> None:
    spark.dataSource.register(StreamTuples)
