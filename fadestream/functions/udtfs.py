"""Table functions for SQL users: they sit behind an exchange by partition key and see K x K rows or one model at a time."""

from __future__ import annotations

import json
from collections.abc import Iterator

import numpy as np
from pyspark.sql import Row, SparkSession
from pyspark.sql.functions import udtf

from fadestream.functions.kernels import sums_of, update


@udtf(returnType="i int, j int")
class AssignmentPairs:
    """Rows (i, j, cost) of a square matrix -> the cheapest one-to-one pairing."""

    def __init__(self) -> None:
        self.cells: dict[tuple[int, int], float] = {}

    def eval(self, row: Row) -> None:
        self.cells[(row["i"], row["j"])] = float(row["cost"])

    def terminate(self) -> Iterator[tuple[int, int]]:
        from fadestream.operators.matching import solve_assignment

        if self.cells:
            n = max(i for i, _ in self.cells) + 1
            cost = np.zeros((n, n))
            for (i, j), v in self.cells.items():
                cost[i, j] = v
            for i, j in enumerate(solve_assignment(cost)[0].tolist()):
                yield i, j


@udtf(returnType="k int, dim int, value double")
class CentroidRows:
    """A model as JSON (list of lists) -> one row a coordinate."""

    def eval(self, model: str) -> Iterator[tuple[int, int, float]]:
        for k, c in enumerate(json.loads(model)):
            for j, v in enumerate(c):
                yield k, j, float(v)


@udtf(returnType="k int, n double, c array<double>")
class LloydStep:
    """Rows (x, w) and a model as JSON -> one update of it by these points."""

    def __init__(self) -> None:
        self.x: list = []
        self.w: list = []
        self.model: np.ndarray | None = None

    def eval(self, row: Row, model: str) -> None:
        self.x.append(row["x"])
        self.w.append(row["w"])
        if self.model is None:
            self.model = np.array(json.loads(model), dtype=float)

    def terminate(self) -> Iterator[tuple[int, float, list[float]]]:
        if self.model is not None:
            s = sums_of(np.array(self.x, dtype=float), np.zeros(len(self.x), dtype=np.int64), self.model, np.array(self.w, dtype=float))
            n, sx = s.n.sum(axis=0), s.sx.sum(axis=0)
            for k, c in enumerate(update(n, sx, self.model).tolist()):
                yield k, float(n[k]), c


def register(spark: SparkSession) -> None:
    spark.udtf.register("assignment_pairs", AssignmentPairs)
    spark.udtf.register("centroid_rows", CentroidRows)
    spark.udtf.register("lloyd_step", LloydStep)
