"""Readers and writers of graphs: tables, edge lists, streams, bucketed incidence, partitions by number of blocks."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

EDGES = T.StructType([T.StructField("src", T.LongType()), T.StructField("dst", T.LongType()), T.StructField("w", T.DoubleType())])


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    """A table, with these columns only read."""
    found = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return found.select(*columns) if columns else found


def edge_list(spark: SparkSession, path: str, sep: str = "\t", weighted: bool = True) -> DataFrame:
    """Edges from text, by a fixed schema; without weights each line counts 1."""
    schema = EDGES if weighted else T.StructType(EDGES.fields[:2])
    found = spark.read.schema(schema).option("sep", sep).option("comment", "#").csv(path)
    return found if weighted else found.withColumn("w", F.lit(1.0))


def json_edges(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(EDGES).json(path)


def stream_edges(spark: SparkSession, path: str, files_per_trigger: int = 1, extra: str = "") -> DataFrame:
    """A stream of Parquet edge files."""
    schema = T.StructType(EDGES.fields + (T.StructType.fromDDL(extra).fields if extra else []))
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def write_incidence(edges: DataFrame, name: str, buckets: int) -> DataFrame:
    """Each edge at both ends, bucketed and sorted by node: written once, joined by node without another exchange."""
    both = edges.where("src <> dst")
    rows = both.select(F.col("src").alias("i"), F.col("dst").alias("j"), F.col("w").alias("w_out"), F.lit(0.0).alias("w_in")).unionAll(both.select("dst", "src", F.lit(0.0), "w"))
    rows.write.mode("overwrite").bucketBy(buckets, "i").sortBy("i").saveAsTable(name)
    return edges.sparkSession.table(name)


def write_partition(assign: DataFrame, blocks: int, path: str) -> None:
    """A partition of the history, under its number of blocks."""
    assign.withColumn("blocks", F.lit(blocks)).write.mode("append").partitionBy("blocks").parquet(path)


class PlantedSource(DataSource):
    """format('planted'): edges of a planted graph of `nodes` nodes in `blocks` equal blocks; options nodes, blocks, degree, within, seed, parts."""

    @classmethod
    def name(cls) -> str:
        return "planted"

    def schema(self) -> str:
        return "src bigint, dst bigint, w double"

    def reader(self, schema: T.StructType) -> DataSourceReader:
        return PlantedReader(self.options)


class PlantedReader(DataSourceReader):
    def __init__(self, options: dict):
        self.n, self.b = int(options.get("nodes", 100)), int(options.get("blocks", 4))
        self.degree, self.within = float(options.get("degree", 8)), float(options.get("within", 0.8))
        self.seed, self.parts = int(options.get("seed", 42)), int(options.get("parts", 4))

    def partitions(self) -> list[InputPartition]:
        return [InputPartition(k) for k in range(self.parts)]

    def read(self, partition: InputPartition) -> Iterator[tuple]:
        import numpy as np

        for i in range(partition.value, self.n, self.parts):
            draw = np.random.default_rng([self.seed, i])
            own: dict[int, float] = {}
            for _ in range(draw.poisson(self.degree)):
                block = i % self.b if draw.random() < self.within else int(draw.integers(self.b))
                j = block + self.b * int(draw.integers(-(-(self.n - block) // self.b)))
                own[j] = own.get(j, 0.0) + 1.0
            yield from ((i, j, w) for j, w in sorted(own.items()))
