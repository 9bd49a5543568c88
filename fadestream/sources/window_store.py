"""The retained window and the models as Parquet folders partitioned by batch number: pruned reads, idempotent writes, recovery.

A batch is written to its own partition folder, so a replay overwrites and never doubles it. The window is a range of batch
numbers; eviction only moves the range, files are unlinked later.
"""

from __future__ import annotations

import tempfile

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

POINTS = "point_id string, x array<double>, batch_seq long"
CENTROIDS = "model_id string, role string, k int, c array<double>, w double, batch_seq long"
STATS = "model_id string, k int, n long, sx array<double>, sxx double, sse double, seq long, batch_seq long"


def shared_root(spark: SparkSession, label: str) -> str:
    """A folder for `label` below spark.checkpoint.dir, or a temporary one where that is unset (tests)."""
    base = spark.conf.get("spark.checkpoint.dir", None) or tempfile.mkdtemp(prefix="fadestream-")
    return f"{base.rstrip('/')}/{label}"


class WindowStore:
    def __init__(self, spark: SparkSession, root: str) -> None:
        self.spark, self.root = spark, root.rstrip("/")

    def _fs(self, path: str):  # noqa: ANN202
        jvm = self.spark.sparkContext._jvm
        p = jvm.org.apache.hadoop.fs.Path(path)
        return p.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()), p

    def append(self, batch: DataFrame, seq: int) -> None:
        batch.select(F.col("point_id").cast("string").alias("point_id"), "x").write.mode("overwrite").parquet(f"{self.root}/points/batch_seq={seq}")

    def batches(self) -> list[int]:
        """Batches present, ascending: what recovery starts from."""
        fs, p = self._fs(f"{self.root}/points")
        if not fs.exists(p):
            return []
        names = [s.getPath().getName() for s in fs.listStatus(p)]
        return sorted(int(n.split("=")[1]) for n in names if n.startswith("batch_seq="))

    def window(self, lo: int, hi: int) -> DataFrame:
        """Points of batches lo..hi; the range prunes partitions, other folders aren't opened."""
        return self.spark.read.schema(POINTS).parquet(f"{self.root}/points").where(F.col("batch_seq").between(lo, hi))

    def drop(self, seq: int) -> None:
        fs, p = self._fs(f"{self.root}/points/batch_seq={seq}")
        fs.delete(p, True)

    def drop_before(self, seq: int) -> list[int]:
        gone = [b for b in self.batches() if b < seq]
        for b in gone:
            fs, p = self._fs(f"{self.root}/points/batch_seq={b}")
            fs.delete(p, True)
        return gone

    def _write(self, rows: list[tuple], schema: str, table: str, seq: int) -> None:
        df = self.spark.createDataFrame(rows, schema).drop("batch_seq")
        df.coalesce(1).write.mode("overwrite").parquet(f"{self.root}/{table}/batch_seq={seq}")

    def write_model(self, model_id: str, seq: int, role: str, c: np.ndarray, w: np.ndarray) -> None:
        rows = [(model_id, role, k, [float(v) for v in c[k]], float(w[k]), seq) for k in range(len(c))]
        self._write(rows, CENTROIDS, f"centroids/{model_id}", seq)

    def write_stats(self, model_id: str, seq: int, sums) -> None:  # noqa: ANN001
        rows = [
            (model_id, k, int(sums.n[i, k]), [float(v) for v in sums.sx[i, k]], float(sums.sxx[i, k]), float(sums.sse[i, k]), int(s), seq)
            for i, s in enumerate(sums.seqs)
            for k in range(sums.n.shape[1])
        ]
        self._write(rows, STATS, f"stats/{model_id}", seq)

    def centroids(self, model_id: str) -> DataFrame:
        return self.spark.read.schema(CENTROIDS).parquet(f"{self.root}/centroids/{model_id}")

    def stats(self, model_id: str) -> DataFrame:
        return self.spark.read.schema(STATS).parquet(f"{self.root}/stats/{model_id}")

    def last_model(self, model_id: str) -> int | None:
        fs, p = self._fs(f"{self.root}/centroids/{model_id}")
        if not fs.exists(p):
            return None
        done = [int(s.getPath().getName().split("=")[1]) for s in fs.listStatus(p) if s.getPath().getName().startswith("batch_seq=") and fs.exists(self._fs(f"{s.getPath()}/_SUCCESS")[1])]
        return max(done, default=None)
