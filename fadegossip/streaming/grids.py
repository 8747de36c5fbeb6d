"""Grids over streams.

A state processor keeps the cells of a site and folds arrivals in order (exact to the sequential algorithm). Where
order doesn't matter, each micro-batch is folded by partitions and merged with the stored grid: a generation is
written under its batch number, so a batch that runs again writes the same generation.
"""

from __future__ import annotations

import sys

import pandas as pd
from pyspark import cloudpickle
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from fadegossip import cells, gossip, query
from fadegossip.decay import DecaySpec
from fadegossip.functions import udfs
from fadegossip.functions.udfs import _fold
from fadegossip.hashing import HashFamily, with_cells
from fadegossip.local import build_local
from fadegossip.schedule import Schedule
from fadegossip.streaming.io import folder

NAMES = ["site", "row", "col", "i1", "f1", "i2", "f2"]
GRID = "site int, row int, col int, i1 long, f1 double, i2 long, f2 double"


class GridProcessor(StatefulProcessor):
    """State of a (site, row): its touched cells."""

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.cells = handle.getMapState("cells", "col int", "i1 long, f1 double, i2 long, f2 double")

    def handleInputRows(self, key, rows, timerValues):
        frame = pd.concat(list(rows)).sort_values(["tick", "seq"])
        out = []
        for col, part in frame.groupby("col"):
            had = self.cells.getValue((int(col),)) if self.cells.containsKey((int(col),)) else (None, 0.0, None, 0.0)
            start = [(had[i], had[i + 1]) for i in (0, 2) if had[i] is not None]
            got = _fold([k for k, _ in start] + part["item_key"].tolist(), [f for _, f in start] + part["x"].tolist())
            now = (got["i1"], got["f1"], got["i2"], got["f2"])
            self.cells.updateValue((int(col),), now)
            out.append((key[0], key[1], int(col), *now))
        yield pd.DataFrame(out, columns=NAMES).astype({"i1": "Int64", "i2": "Int64"})

    def close(self) -> None:
        pass


def stateful_grid(df: DataFrame, spec: DecaySpec, family: HashFamily) -> DataFrame:
    """Streaming (site, item_key, tick, seq long) -> updated cells. Needs the RocksDB state store.

    The processor travels as code: the stream's own worker starts without the driver's import path.
    """
    for module in (sys.modules[__name__], udfs):
        cloudpickle.register_pickle_by_value(module)
    rows = with_cells(df.select("site", "item_key", "tick", "seq", spec.raw().alias("x")), family)
    return rows.groupBy("site", "row").transformWithStateInPandas(GridProcessor(), GRID, "Update", "None")


class MergedGrid:
    """foreachBatch target: stored grid merged with the batch's own."""

    def __init__(self, spark: SparkSession, spec: DecaySpec, family: HashFamily):
        self.spark, self.spec, self.family, self.at, self.last = spark, spec, family, folder(spark), None

    def __call__(self, batch: DataFrame, number: int) -> None:
        fresh = build_local(batch, self.spec, self.family, "preagg")
        before = self.generation(number - 1)
        grid = fresh if before is None else cells.merge_grids(before, fresh, ("site", "row", "col"))
        grid.write.mode("overwrite").parquet(f"{self.at}/grid/{number:08d}")
        self.last = number

    def generation(self, number: int) -> DataFrame | None:
        return self.spark.read.parquet(f"{self.at}/grid/{number:08d}") if number >= 0 else None

    def run(self, df: DataFrame) -> DataFrame | None:
        """Drains the stream and gives the last generation."""
        df.writeStream.foreachBatch(self).option("checkpointLocation", f"{self.at}/log").trigger(availableNow=True).start().awaitTermination()
        return None if self.last is None else self.generation(self.last)


def epoch(grid: DataFrame, schedule: Schedule, family: HashFamily, spec: DecaySpec, support: float, slack: float, asof: int) -> DataFrame:
    """A snapshot of the grids is averaged and asked, while arrivals go on."""
    state = gossip.gossip_by_cell(grid, schedule, family)
    return query.peer_query(state, family, spec, support, slack, asof, gossip.share_table(grid.sparkSession, schedule))


def canonical_stream(df: DataFrame) -> DataFrame:
    """Event types of a streamed events table in canonical form, with a whole-number order."""
    from fadegossip.sources import fingerprint

    tick = F.datediff(F.col("ts").cast("date"), F.lit("2023-12-31").cast("date")).cast("long")
    return df.select((F.col("user_id") % 8).cast("int").alias("site"), fingerprint(F.col("event_type")).alias("item_key"), tick.alias("tick"), F.col("event_id").alias("seq"))
