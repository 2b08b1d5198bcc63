"""Readers and writers: pruned scans of the given tables, coordinate lists in several formats, cells by day, factor tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import shared_folder


def load_table(spark: SparkSession, sf_dir: str, name: str, cols: list[str] | None = None) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*cols) if cols else df


def scratch(spark: SparkSession, name: str) -> str:
    """A folder for round trips, under the shared checkpoint folder."""
    import uuid

    return f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"


def round_trip(df: DataFrame, fmt: str) -> DataFrame:
    """Written and read back with the fixed schema of ``df``."""
    path = scratch(df.sparkSession, fmt)
    writer = df.write.mode("overwrite").format(fmt)
    reader = df.sparkSession.read.schema(df.schema).format(fmt)
    if fmt == "csv":
        writer, reader = writer.option("header", True), reader.option("header", True)
    writer.save(path)
    return reader.load(path)


def write_by_day(df: DataFrame, ts: str, path: str) -> None:
    df.withColumn("day", F.to_date(ts).cast("string")).write.mode("overwrite").partitionBy("day").parquet(path)


def read_day(spark: SparkSession, path: str, day: str) -> DataFrame:
    return spark.read.parquet(path).where(F.col("day") == day)


def register_tensor_zeros(spark: SparkSession) -> None:
    """``spark.read.format('tensor_zeros')``: random cell indices; options dims (comma-separated), n, parts, seed."""
    from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

    class Part(InputPartition):
        def __init__(self, lo: int, hi: int):
            self.lo, self.hi = lo, hi

    class Reader(DataSourceReader):
        def __init__(self, options):
            self.dims = [int(d) for d in options["dims"].split(",")]
            self.n, self.parts, self.seed = int(options.get("n", 1000)), int(options.get("parts", 4)), int(options.get("seed", 0))

        def partitions(self):
            step = -(-self.n // self.parts)
            return [Part(lo, min(self.n, lo + step)) for lo in range(0, self.n, step)]

        def read(self, part):
            mod, mul, inc = 2_147_483_648, 1_103_515_245, 12_345
            for j in range(part.lo, part.hi):
                row = []
                for k, d in enumerate(self.dims):
                    h = self.seed
                    for v in (j, k + 1):
                        h = ((h + v) % mod * mul + inc) % mod
                    row.append((h * mul + inc) % mod // 256 % d)
                yield tuple(row)

    class Zeros(DataSource):
        @classmethod
        def name(cls):
            return "tensor_zeros"

        def schema(self):
            return ", ".join(f"i_{k + 1} bigint" for k in range(len(self.options["dims"].split(","))))

        def reader(self, schema):
            return Reader(self.options)

    spark.dataSource.register(Zeros)
