"""Readers and sinks: series from other formats, a walk generator source, an index source with box pushdown, bucketed storage."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, GreaterThanOrEqual, InputPartition, LessThanOrEqual

POINTS = "series_id bigint, channel int, t bigint, v double"


def read_points(spark: SparkSession, path: str, kind: str = "parquet") -> DataFrame:
    """Points from csv, json, orc, parquet or text (fields parted by commas)."""
    if kind == "text":
        p = F.split("value", ",")
        cast = [F.get(p, F.lit(i)).cast(t).alias(n) for i, (n, t) in enumerate(x.split() for x in POINTS.split(", "))]
        return spark.read.text(path).select(*cast)
    return spark.read.schema(POINTS).format(kind).load(path)


def write_bucketed(points: DataFrame, name: str, buckets: int = 64) -> None:
    """A table bucketed by series, so that joins on series need no shuffle."""
    points.write.mode("overwrite").bucketBy(buckets, "series_id").sortBy("series_id", "t").saveAsTable(name)


def write_results(found: DataFrame, path: str, mode: str = "append", by: str | None = None) -> None:
    """Result sink: append, or overwrite of the partitions that occur."""
    w = found.write.mode(mode)
    if by:
        w = w.partitionBy(by).option("partitionOverwriteMode", "dynamic")
    w.parquet(path)


class WalkSource(DataSource):
    """format("walks"): random-walk points; options n, channels, m, seed. A partition is a range of series."""

    @classmethod
    def name(cls) -> str:
        return "walks"

    def schema(self) -> str:
        return POINTS

    def reader(self, schema) -> DataSourceReader:
        return _WalkReader({k: int(self.options.get(k, v)) for k, v in (("n", 16), ("channels", 4), ("m", 128), ("seed", 42), ("parts", 4))})


class _WalkReader(DataSourceReader):
    def __init__(self, options: dict[str, int]) -> None:
        self.o = options

    def partitions(self) -> list[InputPartition]:
        n, parts = self.o["n"], max(1, min(self.o["parts"], self.o["n"]))
        return [InputPartition((n * i // parts, n * (i + 1) // parts)) for i in range(parts)]

    def read(self, partition: InputPartition) -> Iterator[tuple]:
        import numpy as np

        for s in range(*partition.value):
            for c in range(self.o["channels"]):
                g = np.random.default_rng([self.o["seed"], s, c])
                walk = 100 * g.random() + np.concatenate([[0], np.cumsum(g.normal(0, 10 * g.random(), self.o["m"] - 1))])
                for t, v in enumerate(walk):
                    yield (s, c, t, float(v))


class EntrySource(DataSource):
    """format("mts_entries"): (series_id, first_start, last_start, lo_0, hi_0) of a saved index' Parquet files on a shared path; ranges on lo_0 and hi_0 reach the file statistics.

    Needs spark.sql.python.filterPushdown.enabled. The plain Parquet reader with flattened columns is the way for remote stores.
    """

    @classmethod
    def name(cls) -> str:
        return "mts_entries"

    def schema(self) -> str:
        return "series_id bigint, first_start bigint, last_start bigint, lo_0 double, hi_0 double"

    def reader(self, schema) -> DataSourceReader:
        return _EntryReader(self.options["path"])


class _EntryReader(DataSourceReader):
    def __init__(self, path: str) -> None:
        self.path, self.cuts = path, []

    def pushFilters(self, filters):
        for f in filters:
            if isinstance(f, GreaterThanOrEqual | LessThanOrEqual) and f.attribute in (("lo_0",), ("hi_0",)):
                self.cuts.append((f.attribute[0], ">=" if isinstance(f, GreaterThanOrEqual) else "<=", f.value))
            else:
                yield f

    def read(self, partition) -> Iterator:
        import pyarrow.compute as pc
        import pyarrow.dataset as ds

        where = None
        for name, op, value in self.cuts:
            one = pc.field(name) >= value if op == ">=" else pc.field(name) <= value
            where = one if where is None else where & one
        yield from ds.dataset(self.path).to_batches(columns=["series_id", "first_start", "last_start", "lo_0", "hi_0"], filter=where)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(WalkSource)
    spark.dataSource.register(EntrySource)
