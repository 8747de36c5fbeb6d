"""Item streams in canonical form: site, item, item_key, tick (integer age from the landmark) and seq.

A fixture names an item, a time and the order of simultaneous arrivals of a table; `canonical` rejects arrivals at
or before the landmark and null items or times (rejected() counts them). Scans read only the named columns.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from fadegossip.sources.tables import read_table


def fingerprint(item: Column) -> Column:
    """A string as a number below 2**32: the first eight hex digits of its MD5."""
    return F.conv(F.substring(F.md5(item), 1, 8), 16, 10).cast("long")


def days_since(ts: Column, landmark: str) -> Column:
    return F.datediff(ts.cast("date"), F.lit(landmark).cast("date")).cast("long")


@dataclass(frozen=True)
class Fixture:
    """How a table becomes a stream. item is a string or a whole number; site defaults to a single one."""

    table: str
    item: Callable[[], Column]
    tick: Callable[[], Column]
    order: tuple[str, ...]
    site: Callable[[], Column]
    explode: bool = False


def _words() -> Column:
    return F.explode(F.filter(F.split(F.lower("text"), r"\s+"), lambda w: w != ""))


FIXTURES: dict[str, Fixture] = {
    "types": Fixture("events", lambda: F.col("event_type"), lambda: days_since(F.col("ts"), "2023-12-31"), ("event_id",), lambda: F.col("user_id") % 8),
    "users": Fixture("events", lambda: F.col("user_id"), lambda: days_since(F.col("ts"), "2023-12-31"), ("event_id",), lambda: F.col("event_id") % 16),
    "props": Fixture("events", lambda: F.get_json_object("props", "$.k").cast("long"), lambda: days_since(F.col("ts"), "2023-12-31"), ("event_id",), lambda: F.col("user_id") % 8),
    "suppliers": Fixture("lineitem", lambda: F.col("l_suppkey"), lambda: days_since(F.col("l_shipdate"), "1995-01-01"), ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey"), lambda: F.col("l_orderkey") % 16),
    "parts": Fixture("lineitem", lambda: F.col("l_partkey"), lambda: days_since(F.col("l_shipdate"), "1995-01-01"), ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey"), lambda: F.col("l_orderkey") % 16),
    "priorities": Fixture("orders", lambda: F.col("o_orderpriority"), lambda: days_since(F.col("o_orderdate"), "1994-12-31"), ("o_orderkey",), lambda: F.col("o_custkey") % 8),
    "customers": Fixture("orders", lambda: F.col("o_custkey"), lambda: days_since(F.col("o_orderdate"), "1994-12-31"), ("o_orderkey",), lambda: F.col("o_custkey") % 25),
    "words": Fixture("documents", _words, lambda: F.col("doc_id") + 1, ("doc_id",), lambda: F.regexp_extract("source", "[0-9]+", 0).cast("int"), explode=True),
    "hosts": Fixture("pages", lambda: F.lower(F.regexp_extract("url", "^[a-z]+://([^/]+)", 1)), lambda: F.col("page_id") + 1, ("page_id",), lambda: F.col("page_id") % 4),
    "roles": Fixture("conversations", lambda: F.col("role"), lambda: F.col("turn") + 1, ("conv_id", "turn"), lambda: F.col("conv_id") % 4),
    "labels": Fixture("embeddings", lambda: F.col("label").cast("long"), lambda: F.col("vec_id") + 1, ("vec_id",), lambda: F.col("vec_id") % 8),
}


def canonical(df: DataFrame, item: Column, tick: Column, order: tuple[str, ...], site: Column) -> DataFrame:
    """(site, item, item_key, tick, seq). Numbers are their own key; strings get a fingerprint."""
    rows = df.select(item.alias("item"), tick.cast("long").alias("tick"), F.struct(*[F.col(c) for c in order]).alias("seq"), site.cast("int").alias("site"))
    key = fingerprint(F.col("item")) if dict(rows.dtypes)["item"] == "string" else F.col("item").cast("long")
    return rows.where((F.col("tick") > 0) & F.col("item").isNotNull()).select("site", F.col("item").cast("string").alias("item"), key.alias("item_key"), "tick", "seq")


def rejected(df: DataFrame, item: Column, tick: Column) -> DataFrame:
    """One row: arrivals without item or time, and arrivals at or before the landmark."""
    rows = df.select(item.alias("item"), tick.alias("tick"))
    missing = F.col("item").isNull() | F.col("tick").isNull()
    return rows.agg(F.count_if(missing).alias("dropped_null"), F.count_if(~missing & (F.col("tick") <= 0)).alias("before_landmark"))


def stream(spark: SparkSession, sf_dir: str, name: str, sites: int | None = None) -> DataFrame:
    """A fixture's stream; `sites` deals it anew by its first ordering column."""
    f = FIXTURES[name]
    site = f.site() if sites is None else F.pmod(F.col(f.order[0]), F.lit(sites))
    return canonical(read_table(spark, sf_dir, f.table), f.item(), f.tick(), f.order, site)
