"""Write and read built structures; given tables.

A stored structure is a folder of versions. A version's table is plain Parquet, partitioned by
layer; its manifest, one small JSON row, is written last and makes it visible. Writing a
version again is refused, so retried writers cannot mix bytes."""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.build import BandStructure
from ..params import BandParams

FORMAT = 1


def load(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    """One of the given tables, with only the columns that are asked for."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def write(s: BandStructure, path: str, version: str = "v1") -> None:
    root = f"{path.rstrip('/')}/{version}"
    s.table.write.mode("errorifexists").partitionBy("layer").parquet(f"{root}/table")
    totals = [
        r.asDict()
        for r in s.spark.read.parquet(f"{root}/table")
        .groupBy("layer")
        .agg(*[F.sum(c).alias(c) for c in ("m", "n_in", "n_bumped", "n_redundant", "empty", "row_ops")], F.count(F.lit(1)).alias("shards"))
        .orderBy("layer")
        .collect()
    ]
    manifest = {"format": FORMAT, "params": s.params.to_dict(), "algo": s.algo, "key_seed": s.key_seed, "layers": totals}
    s.spark.createDataFrame([(json.dumps(manifest),)], "value string").coalesce(1).write.mode("errorifexists").text(f"{root}/manifest")


def manifest(spark: SparkSession, path: str, version: str = "v1") -> dict:
    return json.loads(spark.read.text(f"{path.rstrip('/')}/{version}/manifest").first()[0])


def read(spark: SparkSession, path: str, version: str = "v1") -> BandStructure:
    meta = manifest(spark, path, version)
    if meta["format"] != FORMAT:
        raise ValueError(f"format {meta['format']} is not known")
    table = spark.read.parquet(f"{path.rstrip('/')}/{version}/table")
    return BandStructure(BandParams(**meta["params"]), meta["algo"], meta["key_seed"], table)


def register_source(spark: SparkSession) -> None:
    """spark.read.format("bandstore").option("path", ...).load(): the layers of a stored
    structure, a row for each shard and layer, without its bits."""
    from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

    class Reader(DataSourceReader):
        def __init__(self, path: str) -> None:
            self.path = path

        def partitions(self) -> list:
            from pyarrow import dataset

            return [InputPartition(f) for f in dataset.dataset(self.path, format="parquet", partitioning="hive").files]

        def read(self, partition) -> object:
            import pyarrow.parquet as pq

            layer = int(partition.value.split("layer=")[1].split("/")[0])
            names = ["shard", "m", "n_in", "n_bumped", "n_redundant", "empty"]
            for batch in pq.ParquetFile(partition.value).iter_batches(columns=names):
                for row in batch.to_pylist():
                    yield (row["shard"], layer, *[row[c] for c in names[1:]])

    class Source(DataSource):
        @classmethod
        def name(cls) -> str:
            return "bandstore"

        def schema(self) -> str:
            return "shard int, layer int, m long, n_in long, n_bumped long, n_redundant long, empty long"

        def reader(self, schema) -> DataSourceReader:
            return Reader(f"{self.options['path'].rstrip('/')}/{self.options.get('version', 'v1')}/table")

    spark.dataSource.register(Source)
