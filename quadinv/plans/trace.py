"""What a run did: one row for each operation of each node of the recursion."""

from __future__ import annotations

import time
from contextlib import contextmanager
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession

TRACE_DDL = "run string, method string, n long, b int, level int, node string, op string, calls long, elements long, ms double"


@dataclass
class RunTrace:
    run: str = "run"
    method: str = "quadinv"
    n: int = 0
    b: int = 0
    residual: float = 0.0  # probed, of the inverse that was returned
    leaves: list = field(default_factory=list)  # inverses of the leaves, if asked for
    turned: int = 0  # orders of all complements whose sign was turned
    rows: list[tuple] = field(default_factory=list)

    def add(self, level: int, node: str, op: str, calls: int = 1, elements: int = 0, ms: float = 0.0) -> None:
        self.rows.append((self.run, self.method, self.n, self.b, level, node, op, calls, elements, ms))

    @contextmanager
    def timed(self, level: int, node: str, op: str, calls: int = 1, elements: int = 0):
        began = time.perf_counter()
        yield
        self.add(level, node, op, calls, elements, (time.perf_counter() - began) * 1000)

    def count(self, op: str) -> int:
        return sum(r[7] for r in self.rows if r[6] == op)

    def ms(self, op: str) -> float:
        return sum(r[9] for r in self.rows if r[6] == op)

    def frame(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.rows, TRACE_DDL)
