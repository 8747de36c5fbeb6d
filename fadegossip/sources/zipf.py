"""Zipf streams: rows of a table re-keyed by rank, and a data source that makes arrivals."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition
from pyspark.sql.types import LongType

from fadegossip.sources.streams import days_since, fingerprint
from fadegossip.sources.tables import read_table

#: Ranks up to which the table of the law is broadcast and joined by range; beyond, ranks come from binary search in a kernel.
JOINED_UNIVERSE = 1000


def zipf_cdf(rho: float, universe: int) -> list[float]:
    """Values of the bounded Zipf law at ranks 1..universe, the last exactly 1."""
    total, out, upto = sum(r**-rho for r in range(1, universe + 1)), [], 0.0
    for r in range(1, universe + 1):
        upto += r**-rho
        out.append(upto / total)
    out[-1] = 1.0
    return out


def zipf_bounds(spark: SparkSession, rho: float, universe: int) -> DataFrame:
    """(rank, lo, hi) in whole 32-bit steps, so that engines agree on every row."""
    cdf = [0, *(round(x * 2**32) for x in zipf_cdf(rho, universe))]
    return spark.createDataFrame([(r, cdf[r - 1], cdf[r]) for r in range(1, universe + 1)], "rank long, lo long, hi long")


def zipf_stream(spark: SparkSession, sf_dir: str, rho: float, universe: int = JOINED_UNIVERSE, sites: int = 16, seed: int = 0) -> DataFrame:
    """lineitem with a Zipf rank for an item: a hash of the row's keys is a uniform number, and its rank is looked up."""
    rows = read_table(spark, sf_dir, "lineitem")
    salt = [F.lit(str(seed))] if seed else []
    u = fingerprint(F.concat_ws("|", *salt, "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey"))
    base = rows.select(
        F.pmod("l_orderkey", F.lit(sites)).cast("int").alias("site"), u.alias("u"), days_since(F.col("l_shipdate"), "1995-01-01").alias("tick"),
        F.struct("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey").alias("seq"),
    ).where("tick > 0")
    if universe <= JOINED_UNIVERSE:
        law = F.broadcast(zipf_bounds(spark, rho, universe))
        ranked = base.join(law, (F.col("u") >= F.col("lo")) & (F.col("u") < F.col("hi")))
    else:
        ranked = base.withColumn("rank", _rank_udf(rho, universe)(F.col("u")))
    return ranked.select("site", F.col("rank").cast("string").alias("item"), F.col("rank").alias("item_key"), "tick", "seq")


def _rank_udf(rho: float, universe: int):
    edges = np.array([round(x * 2**32) for x in zipf_cdf(rho, universe)], np.int64)

    @F.pandas_udf(LongType())
    def rank(u: pd.Series) -> pd.Series:
        return pd.Series(np.searchsorted(edges, u.to_numpy(), "right") + 1)

    return rank


class ZipfSource(DataSource):
    """spark.read.format("zipf_arrivals"): options rows, rho, universe, seed, partitions, ticks."""

    @classmethod
    def name(cls) -> str:
        return "zipf_arrivals"

    def schema(self) -> str:
        return "item_key long, tick long, seq long"

    def reader(self, schema) -> DataSourceReader:
        return _ZipfReader({k.lower(): v for k, v in self.options.items()})


class _Share(InputPartition):
    def __init__(self, number: int, begin: int, end: int):
        self.number, self.begin, self.end = number, begin, end


class _ZipfReader(DataSourceReader):
    def __init__(self, options: dict):
        get = lambda k, d: type(d)(options.get(k, d))
        self.rows, self.rho, self.universe, self.seed, self.parts, self.ticks = get("rows", 1000), get("rho", 1.2), get("universe", 1000), get("seed", 0), get("partitions", 4), get("ticks", 100)

    def partitions(self):
        edge = [self.rows * i // self.parts for i in range(self.parts + 1)]
        return [_Share(i, edge[i], edge[i + 1]) for i in range(self.parts)]

    def read(self, partition):
        edges = np.array(zipf_cdf(self.rho, self.universe))
        rng = np.random.default_rng([self.seed, partition.number])
        for at in range(partition.begin, partition.end, 65536):
            seq = np.arange(at, min(at + 65536, partition.end))
            item = np.searchsorted(edges, rng.random(len(seq)), "right") + 1
            yield pa.RecordBatch.from_arrays([pa.array(item.astype(np.int64)), pa.array(1 + seq * self.ticks // max(self.rows, 1)), pa.array(seq)], ["item_key", "tick", "seq"])
