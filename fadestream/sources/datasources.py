"""Python Data Sources: a table replayed in ordinal batches, and an endless stream of forged drifts; plus plain formats."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition, SimpleDataSourceStreamReader

POINT = "batch_seq long, ordinal long, x array<double>"


class _Range(InputPartition):
    def __init__(self, seq: int) -> None:
        self.seq = seq


class DriftStream:
    """Batch `seq` of a seeded stream: k clusters in d dimensions whose centres jump by sqrt(eps) spreads every `period` batches."""

    def __init__(self, options: dict) -> None:
        self.k, self.d, self.n = int(options.get("k", 5)), int(options.get("d", 4)), int(options.get("n", 500))
        self.period, self.eps, self.seed = int(options.get("period", 10)), float(options.get("eps", 1.0)), int(options.get("seed", 0))
        self.batches = int(options.get("batches", 20))

    def rows(self, seq: int) -> Iterator[tuple]:
        base = np.random.default_rng([self.seed, 1])
        centres = base.normal(scale=6.0, size=(self.k, self.d))
        for c in range(1, seq // self.period + 1):
            g = np.random.default_rng([self.seed, 2, c]).normal(size=(self.k, self.d))
            centres = centres + np.sqrt(self.eps * self.d) * g / np.linalg.norm(g, axis=1, keepdims=True)
        rng = np.random.default_rng([self.seed, 3, seq])
        x = centres[rng.integers(0, self.k, self.n)] + rng.normal(size=(self.n, self.d))
        for i, v in enumerate(x.tolist()):
            yield seq, seq * self.n + i, v


class _ForgeReader(DataSourceReader):
    def __init__(self, stream: DriftStream) -> None:
        self.stream = stream

    def partitions(self) -> list[InputPartition]:
        return [_Range(s) for s in range(self.stream.batches)]

    def read(self, partition: _Range) -> Iterator[tuple]:
        return self.stream.rows(partition.seq)


class _ForgeStream(SimpleDataSourceStreamReader):
    def __init__(self, stream: DriftStream) -> None:
        self.stream = stream

    def initialOffset(self) -> dict:  # noqa: N802
        return {"seq": 0}

    def read(self, start: dict) -> tuple[Iterator[tuple], dict]:
        s = start["seq"]
        if s >= self.stream.batches:
            return iter(()), start
        return iter(list(self.stream.rows(s))), {"seq": s + 1}

    def readBetweenOffsets(self, start: dict, end: dict) -> Iterator[tuple]:  # noqa: N802
        for s in range(start["seq"], end["seq"]):
            yield from self.stream.rows(s)


class DriftForgeSource(DataSource):
    """format("drift_forge"): options k, d, n, period, eps, seed, batches."""

    @classmethod
    def name(cls) -> str:
        return "drift_forge"

    def schema(self) -> str:
        return POINT

    def reader(self, schema) -> DataSourceReader:  # noqa: ANN001
        return _ForgeReader(DriftStream(self.options))

    def simpleStreamReader(self, schema) -> SimpleDataSourceStreamReader:  # noqa: ANN001, N802
        return _ForgeStream(DriftStream(self.options))


class _Table:
    """Rows of a Parquet file by ordinal, in batches of n, read through Arrow's file systems."""

    def __init__(self, options: dict) -> None:
        self.path, self.n, self.columns = options["path"], int(options.get("n", 500)), options["columns"].split(",")

    def _file(self):  # noqa: ANN202
        import pyarrow.dataset as ds

        return ds.dataset(self.path, format="parquet")

    def count(self) -> int:
        return self._file().count_rows()

    def rows(self, seq: int) -> Iterator[tuple]:
        lo = seq * self.n
        part = self._file().scanner(columns=self.columns).take(np.arange(lo, min(lo + self.n, self.count())))
        cols = [np.asarray(part.column(c).to_pylist(), dtype=float) for c in self.columns]
        for i, v in enumerate(np.stack(cols, axis=1).tolist()):
            yield seq, lo + i, v


class _ReplayReader(DataSourceReader):
    def __init__(self, table: _Table) -> None:
        self.table = table

    def partitions(self) -> list[InputPartition]:
        return [_Range(s) for s in range(-(-self.table.count() // self.table.n))]

    def read(self, partition: _Range) -> Iterator[tuple]:
        return self.table.rows(partition.seq)


class _ReplayStream(SimpleDataSourceStreamReader):
    def __init__(self, table: _Table) -> None:
        self.table = table

    def initialOffset(self) -> dict:  # noqa: N802
        return {"seq": 0}

    def read(self, start: dict) -> tuple[Iterator[tuple], dict]:
        s = start["seq"]
        if s * self.table.n >= self.table.count():
            return iter(()), start
        return iter(list(self.table.rows(s))), {"seq": s + 1}

    def readBetweenOffsets(self, start: dict, end: dict) -> Iterator[tuple]:  # noqa: N802
        for s in range(start["seq"], end["seq"]):
            yield from self.table.rows(s)


class OrdinalReplaySource(DataSource):
    """format("ordinal_replay"): options path, columns (comma-separated), n. One batch of exactly n a trigger."""

    @classmethod
    def name(cls) -> str:
        return "ordinal_replay"

    def schema(self) -> str:
        return POINT

    def reader(self, schema) -> DataSourceReader:  # noqa: ANN001
        return _ReplayReader(_Table(self.options))

    def simpleStreamReader(self, schema) -> SimpleDataSourceStreamReader:  # noqa: ANN001, N802
        return _ReplayStream(_Table(self.options))


def register(spark: SparkSession) -> None:
    spark.dataSource.register(DriftForgeSource)
    spark.dataSource.register(OrdinalReplaySource)


def write_points(df: DataFrame, path: str, fmt: str) -> None:
    """Points in parquet, orc or json as they are; in csv or text with the vector as a JSON string."""
    if fmt in ("csv", "text"):
        flat = df.withColumn("x", F.to_json("x"))
        if fmt == "text":
            flat = flat.select(F.to_json(F.struct(*flat.columns)).alias("value"))
        flat.write.mode("overwrite").format(fmt).save(path)
    else:
        df.write.mode("overwrite").format(fmt).save(path)


def read_points(spark: SparkSession, path: str, fmt: str, schema: str = "point_id string, x array<double>, batch_seq long") -> DataFrame:
    if fmt == "csv":
        flat = spark.read.schema(schema.replace("array<double>", "string")).csv(path)
        return flat.withColumn("x", F.from_json("x", "array<double>"))
    if fmt == "text":
        rows = spark.read.text(path).select(F.from_json("value", schema.replace("array<double>", "string")).alias("r")).select("r.*")
        return rows.withColumn("x", F.from_json("x", "array<double>"))
    return spark.read.schema(schema).format(fmt).load(path)
