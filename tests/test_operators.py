"""Operators on odd rows."""

import datetime as dt

from fadegossip.operators.windows import range_counts
from fadegossip.plans import checks


def test_range_counts(spark):
    start = dt.datetime(2024, 1, 1)
    times = [0, 0.5, 1, 9, 10, 10.9, 11, 12, 3599, 3600, 3605, 7200, 7210, 7211, None, None]
    rows = [(i, kind, None if s is None else start + dt.timedelta(seconds=s)) for i, (kind, s) in enumerate((k, s) for k in ("a", "b", None) for s in times + times[:4])]
    df = range_counts(spark.createDataFrame(rows, "event_id long, event_type string, ts timestamp_ntz"), 10)
    second = lambda t: None if t is None else int((t - start).total_seconds())
    inside = lambda x, y: x is y if x is None or y is None else y - 10 <= x <= y
    want = {i: sum(k == kind and inside(second(u), second(t)) for _, k, u in rows) for i, kind, t in rows}
    assert {r.event_id: r.n for r in df.collect()} == want


def test_range_counts_need_no_sliding_frame(spark, small):
    from fadegossip.operators.windows import QUERIES

    text = checks.plan_text(QUERIES["op_range_frame"](spark, small))
    assert "-604800" not in text and "604800 PRECEDING" not in text
