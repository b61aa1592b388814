"""Who is responsible for what: a tiling of the grid by leaves, and for each leaf one worker or a split of
its terms among several. All partitioners, of space, of text, or of both, end in this form.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from geoherald.functions.geometry import Grid

#: Terms with a place of their own; the others go by hash, so a lexicon is never gathered.
HEAD_TERMS = 50_000
#: Head terms of all leaves together up to which they are broadcast.
BROADCAST_HEADS = 500_000


@dataclass
class Leaf:
    """A rectangle of cells, ``[x0, x1)`` by ``[y0, y1)``, with a worker for each of its parts.

    With one part, all terms are that worker's. With several, ``terms`` places the known terms in
    parts and any other term goes to the part that its hash names.
    """

    x0: int
    y0: int
    x1: int
    y1: int
    workers: list[int] = field(default_factory=lambda: [0])
    terms: dict[str, int] = field(default_factory=dict)
    load: float = 0.0

    @property
    def by_text(self) -> bool:
        return len(self.workers) > 1


@dataclass
class Assignment:
    """A partition of the work among ``m`` workers."""

    grid: Grid
    m: int
    leaves: list[Leaf]
    name: str = ""
    version: int = 0
    feasible: bool = True

    def check(self) -> None:
        """Every cell lies in one leaf and every part has a worker; raises otherwise."""
        seen = [0] * (self.grid.n * self.grid.n)
        for leaf in self.leaves:
            for cy in range(leaf.y0, leaf.y1):
                for cx in range(leaf.x0, leaf.x1):
                    seen[cy * self.grid.n + cx] += 1
            if not leaf.workers or not all(0 <= w < self.m for w in leaf.workers):
                raise ValueError(f"leaf without a worker: {leaf}")
            if any(not 0 <= p < len(leaf.workers) for p in leaf.terms.values()):
                raise ValueError("a term in a part that is not there")
        if any(n != 1 for n in seen):
            raise ValueError("leaves don't tile the world")

    def cells(self, spark: SparkSession) -> DataFrame:
        """``cell, leaf, workers``: one row per cell of the grid, whatever the data."""
        rows = [(cy * self.grid.n + cx, k, leaf.workers) for k, leaf in enumerate(self.leaves) for cy in range(leaf.y0, leaf.y1) for cx in range(leaf.x0, leaf.x1)]
        return F.broadcast(spark.createDataFrame(rows, "cell int, leaf int, workers array<int>"))

    def head_terms(self, spark: SparkSession) -> DataFrame:
        """``leaf, term, part``: at most ``HEAD_TERMS`` for each leaf cut by text."""
        rows = [(k, t, p) for k, leaf in enumerate(self.leaves) if leaf.by_text for t, p in leaf.terms.items()]
        schema = T.StructType([T.StructField("leaf", T.IntegerType()), T.StructField("term", T.StringType()), T.StructField("part", T.IntegerType())])
        table = spark.createDataFrame(rows, schema)
        return F.broadcast(table) if len(rows) <= BROADCAST_HEADS else table

    def leaf_table(self, spark: SparkSession) -> DataFrame:
        """``leaf, x0, y0, x1, y1, workers``: one row per leaf, of which there are no more than cells."""
        return F.broadcast(spark.createDataFrame([(k, leaf.x0, leaf.y0, leaf.x1, leaf.y1, leaf.workers) for k, leaf in enumerate(self.leaves)], "leaf int, x0 int, y0 int, x1 int, y1 int, workers array<int>"))

    def _leaf_of(self, df: DataFrame, by_tree: bool) -> DataFrame:
        """Adds ``leaf`` and ``workers`` by the grid's cell, or by going through the rectangles of the leaves."""
        if not by_tree:
            return df.join(self.cells(df.sparkSession), "cell")
        at = [f"__{c}" for c in ("x0", "y0", "x1", "y1")]
        leaves = self.leaf_table(df.sparkSession).toDF("leaf", *at, "workers")
        cx, cy = F.col("cell") % self.grid.n, F.floor(F.col("cell") / self.grid.n)
        return df.join(leaves, (cx >= F.col("__x0")) & (cx < F.col("__x1")) & (cy >= F.col("__y0")) & (cy < F.col("__y1"))).drop(*at)

    def place(self, df: DataFrame, by_tree: bool = False) -> DataFrame:
        """Adds ``worker`` to rows with ``cell`` and ``term``; ``by_tree`` finds the leaf without the grid.

        A grid without text leaves is a broadcast of one row per cell; head terms are broadcast too, up to
        ``BROADCAST_HEADS`` of them.
        """
        spark = df.sparkSession
        found = self._leaf_of(df, by_tree)
        if not any(leaf.by_text for leaf in self.leaves):
            return found.withColumn("worker", F.col("workers")[0]).drop("leaf", "workers")
        found = found.join(self.head_terms(spark), ["leaf", "term"], "left")
        part = F.coalesce("part", hashed_part(F.col("term"), F.size("workers")))
        return found.withColumn("worker", F.get("workers", part)).drop("leaf", "workers", "part")

    def chart(self) -> tuple[np.ndarray, list[np.ndarray], list[tuple[np.ndarray, np.ndarray]]]:
        """Whose a term is in a cell, in arrays for tasks (``cellmatch.Chart``): the leaf of each cell, the leaves' workers,
        and codes and parts of their head terms."""
        leaf_of = np.zeros((self.grid.n, self.grid.n), dtype=np.int64)
        for k, leaf in enumerate(self.leaves):
            leaf_of[leaf.y0 : leaf.y1, leaf.x0 : leaf.x1] = k
        heads = []
        for leaf in self.leaves:
            terms = sorted((code_of(t), p) for t, p in leaf.terms.items()) if leaf.by_text else []
            heads.append((np.array([c for c, _ in terms], dtype=np.int64), np.array([p for _, p in terms], dtype=np.int64)))
        return leaf_of.ravel(), [np.array(leaf.workers, dtype=np.int64) for leaf in self.leaves], heads

    def places(self) -> np.ndarray | None:
        """A number for each cell, the same for cells that the same workers share in the same way; that of its worker where there
        is one. None if workers are too many to be bits of a number."""
        if self.m > 62:
            return None
        shared: dict[tuple, int] = {}
        out = np.zeros((self.grid.n, self.grid.n), dtype=np.int64)
        for leaf in self.leaves:
            place = shared.setdefault((*leaf.workers, id(leaf.terms)), self.m + len(shared)) if leaf.by_text else leaf.workers[0]
            out[leaf.y0 : leaf.y1, leaf.x0 : leaf.x1] = place
        return out.ravel()

    def describe(self, spark: SparkSession) -> DataFrame:
        """One row per leaf: its rectangle, kind, workers and number of head terms."""
        rows = [(k, leaf.x0, leaf.y0, leaf.x1, leaf.y1, "text" if leaf.by_text else "space", leaf.workers, len(leaf.terms), float(leaf.load)) for k, leaf in enumerate(self.leaves)]
        return spark.createDataFrame(rows, "leaf int, x0 int, y0 int, x1 int, y1 int, kind string, workers array<int>, n_terms int, load double")


def hashed_part(term: Column, parts: Column) -> Column:
    return F.pmod(F.xxhash64(term), parts.cast("long")).cast("int")


def code_of(term: str) -> int:
    """The 64-bit code of a term, as the engine has it."""
    value = xxhash.xxh64_intdigest(term.encode(), seed=42)
    return value - (1 << 64) if value >> 63 else value


def part_of(term: str, parts: int) -> int:
    """As :func:`hashed_part`, for the planner."""
    return code_of(term) % parts


def whole_world(grid: Grid, m: int, workers: list[int] | None = None, terms: dict[str, int] | None = None, name: str = "") -> Assignment:
    """One leaf over all cells; with several workers, a partition by text only."""
    return Assignment(grid, m, [Leaf(0, 0, grid.n, grid.n, workers or [0], terms or {})], name)
