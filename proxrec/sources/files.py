"""Rating dumps in common formats, a source of planted low-rank ratings, and sinks for lists and measures."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from proxrec.operators.ratings import canonical


def read_ratings(spark: SparkSession, path: str, fmt: str, user: str = "user_id", item: str = "item_id", value: str = "rating", cap: float | None = None) -> DataFrame:
    """Unique ratings from csv (with a header), json, orc, parquet or text lines of four fields between double colons."""
    if fmt == "colons":
        part = F.split("value", "::")
        rows = spark.read.text(path).select(part[0].cast("long").alias("user_id"), part[1].cast("long").alias("item_id"), part[2].cast("double").alias("rating"))
        return canonical(rows, "user_id", "item_id", "rating", cap=cap)
    reader = spark.read.option("header", True).option("inferSchema", True) if fmt == "csv" else spark.read
    return canonical(reader.format(fmt).load(path), user, item, value, cap=cap)


def write_partitioned(rows: DataFrame, path: str, *columns: str) -> None:
    """Writes Parquet by the given columns; a repeated run replaces its own partitions only."""
    rows.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy(*columns).parquet(path)


def export_lists(recs: DataFrame, path: str, fmt: str = "json") -> None:
    """One line a user: its items in order, with scores."""
    lists = recs.groupBy("user_id").agg(F.array_sort(F.collect_list(F.struct("rank", "item_id", "score"))).alias("items"))
    if fmt == "csv":
        lists = lists.select("user_id", F.array_join(F.transform("items", lambda x: x["item_id"].cast("string")), " ").alias("items"))
    lists.write.mode("overwrite").format(fmt).save(path)


class _Users(InputPartition):
    def __init__(self, start: int, stop: int):
        self.start, self.stop = start, stop


class _PlantedReader(DataSourceReader):
    def __init__(self, options: dict):
        self.users, self.items, self.rank = int(options.get("users", 200)), int(options.get("items", 50)), int(options.get("rank", 3))
        self.noise, self.seed, self.parts = float(options.get("noise", 0.01)), int(options.get("seed", 1)), int(options.get("partitions", 4))

    def partitions(self):
        cuts = np.linspace(0, self.users, self.parts + 1).astype(int).tolist()
        return [_Users(a, b) for a, b in zip(cuts, cuts[1:], strict=False)]

    def read(self, partition):
        sides = np.abs(np.random.default_rng(self.seed).standard_normal((self.items, self.rank)))
        for u in range(partition.start, partition.stop):
            rng = np.random.default_rng([self.seed, u])
            row = np.abs(rng.standard_normal(self.rank)) @ sides.T + self.noise * np.abs(rng.standard_normal(self.items))
            for i, x in enumerate(row.tolist()):
                yield (u, i, x)


class PlantedRatings(DataSource):
    """Ratings of a known low rank plus noise: spark.dataSource.register(PlantedRatings), then format planted_ratings."""

    @classmethod
    def name(cls) -> str:
        return "planted_ratings"

    def schema(self) -> str:
        return "user_id long, item_id long, rating double"

    def reader(self, schema):
        return _PlantedReader(self.options)
