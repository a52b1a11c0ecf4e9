"""Public communication graphs: fixtures, random sweeps, and a data source that lists them."""

from __future__ import annotations

import random

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

#: The main graph's chords beside the ring 0..9, and the sweep's edge counts.
MAIN_CHORDS = ((0, 3), (0, 5), (0, 7), (4, 8), (2, 6), (1, 8))
SWEEP_EDGES = (12, 13, 17, 19, 27, 29, 35, 37, 41)

Pairs = list[tuple[int, int]]


def ring(n: int) -> Pairs:
    return sorted({(min(i, (i + 1) % n), max(i, (i + 1) % n)) for i in range(n)} if n > 1 else set())


def main_graph() -> Pairs:
    return sorted(set(ring(10)) | set(MAIN_CHORDS))


def complete(n: int) -> Pairs:
    return [(i, j) for i in range(n) for j in range(i + 1, n)]


def circulant(n: int, steps: tuple[int, ...]) -> Pairs:
    return sorted({(min(i, (i + s) % n), max(i, (i + s) % n)) for i in range(n) for s in steps})


def petersen() -> Pairs:
    return sorted([*ring(5), *((i, i + 5) for i in range(5)), *((5 + min(i, (i + 2) % 5), 5 + max(i, (i + 2) % 5)) for i in range(5))])


def random_connected(n: int, edges: int, seed: int) -> Pairs:
    """A random tree, then random further edges, until there are `edges`."""
    rng = random.Random(f"{n}:{edges}:{seed}")
    order = rng.sample(range(n), n)
    out = {tuple(sorted((order[i], order[rng.randrange(i)]))) for i in range(1, n)}
    rest = [p for p in complete(n) if p not in out]
    return sorted(out | set(rng.sample(rest, edges - len(out))))


def named(kind: str, n: int = 10) -> Pairs:
    made = {
        "main": main_graph,
        "ring": lambda: ring(n),
        "complete": lambda: complete(n),
        "petersen": petersen,
        "circulant": lambda: circulant(n, (1, 5)),
        "unsafe": lambda: sorted(set(ring(10)) | {(0, 2)}),
        "split": lambda: ring(5) + [(a + 5, b + 5) for a, b in ring(5)],
    }
    if kind not in made:
        raise ValueError(f"no graph named {kind}; there are {sorted(made)}")
    return made[kind]()


def edges_df(spark: SparkSession, pairs: Pairs) -> DataFrame:
    """(src, dst), both directions of every edge."""
    return spark.createDataFrame([e for a, b in pairs for e in ((a, b), (b, a))], "src int, dst int")


class TopologySource(DataSource):
    """spark.read.format("topology").option("kind", "ring").option("n", "10")"""

    @classmethod
    def name(cls) -> str:
        return "topology"

    def schema(self) -> str:
        return "src int, dst int"

    def reader(self, schema) -> DataSourceReader:
        return _TopologyReader(self.options.get("kind", "main"), int(self.options.get("n", "10")))


class _TopologyReader(DataSourceReader):
    def __init__(self, kind: str, n: int):
        self.kind, self.n = kind, n

    def partitions(self):
        return [InputPartition(0)]

    def read(self, partition):
        for a, b in named(self.kind, self.n):
            yield a, b
            yield b, a


def register(spark: SparkSession) -> None:
    spark.dataSource.register(TopologySource)
