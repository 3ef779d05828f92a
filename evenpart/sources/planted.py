"""A Python data source that generates a planted block graph, a range of its rows per task.

``spark.dataSource.register(PlantedSource)``, then ``spark.read.format("planted").options(n=256, blocks=4).load()``.
The coin of a pair is the md5 of its ids, as in ``graphs.planted``, so any number of tasks gives the same edges.
"""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

DEFAULTS = {"n": "256", "blocks": "4", "p_in": "0.9", "p_out": "0.1", "seed": "42", "tasks": "8"}


class RowRange(InputPartition):
    """Edges whose smaller end lies in [lo, hi)."""

    def __init__(self, lo: int, hi: int) -> None:
        super().__init__((lo, hi))
        self.lo, self.hi = lo, hi


class PlantedReader(DataSourceReader):
    def __init__(self, options: dict) -> None:
        got = {k: options.get(k, v) for k, v in DEFAULTS.items()}
        self.n, self.blocks, self.tasks, self.seed = int(got["n"]), int(got["blocks"]), int(got["tasks"]), got["seed"]
        self.p_in, self.p_out = float(got["p_in"]), float(got["p_out"])
        if not 1 <= self.blocks <= max(self.n, 1) or not 0 <= self.p_out <= 1 or not 0 <= self.p_in <= 1 or self.tasks < 1:
            raise ValueError(f"planted: unusable options {got}")

    def partitions(self) -> list[RowRange]:
        # row i has n - 1 - i partners: cuts at equal areas of the triangle, not at equal numbers of rows
        at = [round(self.n * (1 - (1 - t / self.tasks) ** 0.5)) for t in range(self.tasks + 1)]
        return [RowRange(lo, hi) for lo, hi in zip(at, at[1:], strict=False) if hi > lo] or [RowRange(0, 0)]

    def read(self, partition: RowRange) -> Iterator[tuple[int, int, float]]:
        from hashlib import md5

        block = lambda i: i * self.blocks // self.n
        for i in range(partition.lo, partition.hi):
            for j in range(i + 1, self.n):
                coin = int(md5(f"{i}:{j}:{self.seed}".encode()).hexdigest()[:8], 16) / 2**32  # noqa: S324
                if coin < (self.p_in if block(i) == block(j) else self.p_out):
                    yield i, j, 1.0


class PlantedSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "planted"

    def schema(self) -> str:
        return "src long, dst long, w double"

    def reader(self, schema) -> PlantedReader:
        return PlantedReader(self.options)
