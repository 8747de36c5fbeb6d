"""Pairwise independent hash functions, the same at every site: ((a * key + b) mod P) mod width."""

from __future__ import annotations

import random
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

P = 2147483647
# fixed values: multipliers and offsets of the first rows
FIRST = ((1103515245, 12345), (48271, 11), (16807, 7), (69621, 3))


@dataclass(frozen=True)
class HashFamily:
    depth: int
    width: int
    seed: int | None = None

    @property
    def params(self) -> list[tuple[int, int]]:
        if self.seed is None and self.depth <= len(FIRST):
            return list(FIRST[: self.depth])
        rng = random.Random(f"rows-{self.seed}")
        drawn = [(rng.randrange(1, P), rng.randrange(P)) for _ in range(self.depth)]
        return drawn if self.seed is not None else [*FIRST, *drawn[len(FIRST) :]]

    def cell(self, row: int, key: Column) -> Column:
        """Column of a key in a row; keys of any size are reduced first, so that products fit a long."""
        a, b = self.params[row]
        return (F.pmod(F.pmod(key, F.lit(P)) * F.lit(a) + F.lit(b), F.lit(P)) % F.lit(self.width)).cast("int")

    def cells(self, key: Column) -> Column:
        """Array of (row, col) structs, one for each row."""
        return F.array(*[F.struct(F.lit(r).alias("row"), self.cell(r, key).alias("col")) for r in range(self.depth)])

    def table(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame([(r, a, b) for r, (a, b) in enumerate(self.params)], "row int, a long, b long")

    def sql_col(self, key: str, a: str = "a", b: str = "b") -> str:
        """The same column as SQL text, for oracles and SQL users."""
        return f"((({a} * ({key} % {P}) + {b}) % {P}) % {self.width})"


def with_cells(df: DataFrame, family: HashFamily) -> DataFrame:
    """A row for each row of the grid: adds (row, col). The family is folded into the plan as literals."""
    return df.withColumn("_cell", F.explode(family.cells(F.col("item_key")))).withColumns({"row": F.col("_cell.row"), "col": F.col("_cell.col")}).drop("_cell")
