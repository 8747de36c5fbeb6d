"""What physical plans do: pruned and pushed scans, combined sums, one shuffle for all rounds."""

from pyspark.sql import functions as F

from fadegossip import gossip
from fadegossip.decay import DecaySpec
from fadegossip.hashing import HashFamily
from fadegossip.local import preaggregate
from fadegossip.operators import QUERIES
from fadegossip.plans import operators_of, pushed_filters, read_columns, shuffles
from fadegossip.schedule import draw_exchanges
from fadegossip.sources import stream


def test_scan_reads_what_it_needs(spark, small):
    df = QUERIES["op_scan_pruned"](spark, small)
    assert "ts:timestamp_ntz,user_id:bigint" in read_columns(df)
    assert any("GreaterThanOrEqual(ts" in x for x in pushed_filters(df))


def test_items_are_summed_before_the_shuffle(spark, small):
    df = preaggregate(stream(spark, small, "types"), DecaySpec("poly"))
    assert operators_of(df).count("HashAggregate") == 2 and shuffles(df) == 1
    assert all("value" not in c for c in read_columns(df))


def test_all_rounds_in_one_shuffle(spark, small):
    grid = spark.createDataFrame([(0, 0, 0, 1, 1.0, None, 0.0)], "site int, row int, col int, i1 long, f1 double, i2 long, f2 double")
    df = gossip.gossip_by_cell(grid, draw_exchanges(None, 8, 24, 1, 0), HashFamily(1, 8))
    assert shuffles(df) == 1 and "BroadcastExchange" not in operators_of(df)


def test_small_sides_are_broadcast(spark, small):
    assert "BroadcastHashJoin" in operators_of(QUERIES["op_range_join"](spark, small))
    assert "SortMergeJoin" in operators_of(QUERIES["op_shuffle_join_merge"](spark, small))


def test_empty_stream(spark, small):
    from fadegossip.local import build_local

    none = stream(spark, small, "types").where(F.lit(False))
    for mode in ("arrival", "preagg", "partition"):
        assert build_local(none, DecaySpec(), HashFamily(2, 4), mode).count() == 0
