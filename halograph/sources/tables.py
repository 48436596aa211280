"""The given tables as Parquet, with round trips through other formats."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..session import fresh_path


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def through(df: DataFrame, fmt: str, **options: str) -> DataFrame:
    """Write df in another format and read it with its own schema."""
    path = fresh_path(df.sparkSession, fmt)
    df.write.format(fmt).options(**options).save(path)
    return df.sparkSession.read.format(fmt).schema(df.schema).options(**options).load(path)


def write_by_part(df: DataFrame, path: str, part: str = "part") -> None:
    """One folder per part, so that a rank reads its own rows only."""
    df.repartition(part).write.partitionBy(part).parquet(path)


class RingGraph(DataSource):
    """A made graph as a source of its own: vertex i leads to the `reach` vertices after it on a ring. Each part is made where it is read."""

    @classmethod
    def name(cls) -> str:
        return "ring_graph"

    def schema(self) -> str:
        return "src bigint, dst bigint"

    def reader(self, schema):  # noqa: ANN001, ANN201 - the interface's
        o = self.options
        return RingReader(int(o.get("vertices", 10)), int(o.get("reach", 1)), int(o.get("parts", 1)))


class RingReader(DataSourceReader):
    def __init__(self, vertices: int, reach: int, parts: int) -> None:
        self.vertices, self.reach, self.parts = vertices, reach, parts

    def partitions(self) -> list[InputPartition]:
        return [InputPartition(k) for k in range(self.parts)]

    def read(self, partition: InputPartition):  # noqa: ANN201
        import pyarrow as pa

        low, high = (self.vertices * k // self.parts for k in (partition.value, partition.value + 1))
        src = [i for i in range(low, high) for _ in range(self.reach)]
        dst = [(i + k) % self.vertices for i in range(low, high) for k in range(1, self.reach + 1)]
        yield pa.record_batch([pa.array(src, pa.int64()), pa.array(dst, pa.int64())], names=["src", "dst"])


def register_sources(spark: SparkSession) -> None:
    spark.dataSource.register(RingGraph)
