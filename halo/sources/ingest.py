"""Readers and writers with explicit schemas, and a process source."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


@dataclass(frozen=True)
class SeriesSpec:
    """How a table becomes a series: time column, step and origin in microseconds, dimension, value, aggregate."""

    time: str
    step_us: int
    origin_us: int
    dim: str | None = None
    value: str | None = None
    how: str = "count"


def read(spark: SparkSession, folder: str, name: str, columns: list[str] | None = None, where: Column | str | None = None) -> DataFrame:
    df = spark.read.parquet(f"{folder}/{name}.parquet")
    df = df.where(where) if where is not None else df
    return df.select(*columns) if columns else df


def read_as(spark: SparkSession, path: str, fmt: str, schema: str, **options) -> DataFrame:
    return spark.read.format(fmt).schema(schema).options(**options).load(path)


def stream(spark: SparkSession, path: str, schema, max_files: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", max_files).parquet(path)


def write(df: DataFrame, path: str, fmt: str = "parquet", partition_by: tuple[str, ...] = (), mode: str = "overwrite") -> None:
    w = df.write.format(fmt).mode(mode)
    (w.partitionBy(*partition_by) if partition_by else w).save(path)


def micros(ts: Column) -> Column:
    """Microseconds since 1970 of the wall clock, whatever the session's time zone."""
    seconds = F.hour(ts) * 3600 + F.minute(ts) * 60
    fraction = (F.extract(F.lit("SECOND"), ts) * 1_000_000).cast("bigint")
    return F.datediff(F.to_date(ts), F.lit("1970-01-01").cast("date")).cast("bigint") * 86_400_000_000 + seconds.cast("bigint") * 1_000_000 + fraction


class _Range(InputPartition):
    def __init__(self, first: int, last: int):
        self.first, self.last = first, last


class _ProcessReader(DataSourceReader):
    def __init__(self, options):
        self.n, self.seed = int(options.get("n", 1000)), int(options.get("seed", 1))
        self.a, self.b = float(options.get("a", 0.0)), float(options.get("b", 0.0))
        self.parts = int(options.get("partitions", 4))

    def partitions(self):
        step = -(-self.n // self.parts)
        return [_Range(k, min(self.n, k + step)) for k in range(0, self.n, step)]

    def read(self, part):
        import numpy as np

        def noise(k: int) -> float:  # the same draw for an index in whatever partition
            return float(np.random.Generator(np.random.Philox(key=self.seed, counter=k & 0xFFFFFFFF)).standard_normal())

        warm = 200 if self.a else 1
        x, before = 0.0, 0.0
        for k in range(part.first - warm, part.last):
            e = noise(k)
            x, before = self.a * x + e + self.b * before, e
            if k >= part.first:
                yield (k, x)


class ProcessSource(DataSource):
    """An ARMA(1,1) series from counter-based noise: options n, seed, a, b, partitions."""

    @classmethod
    def name(cls):
        return "halo_process"

    def schema(self):
        return "idx bigint, v double"

    def reader(self, schema):
        return _ProcessReader(self.options)


def process_source(spark: SparkSession, n: int, seed: int = 1, a: float = 0.0, b: float = 0.0) -> DataFrame:
    spark.dataSource.register(ProcessSource)
    return spark.read.format("halo_process").options(n=n, seed=seed, a=a, b=b).load()
