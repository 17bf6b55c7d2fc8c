"""The entry file, lines in and out, streams, functions."""

import __spark_entry__ as entry
import pytest

from vertimine.functions import itemset as fn
from vertimine.plans import mine as plan
from vertimine.sources import baskets as b
from vertimine.streaming import windows


def test_entry_and_names(spark):
    assert entry.entry(spark).columns == ["itemset", "k", "support"]
    names, sql = entry.queries(), entry.oracle_sql()
    assert set(sql) <= set(names) and len(names) > 200


def test_lines_round_trip(spark, sf, tmp_path):
    rows = b.user_day_types(spark, sf).rows
    b.write_lines(rows, f"file://{tmp_path}/lines")
    again = b.read_lines(spark, f"file://{tmp_path}/lines")
    counts = lambda r: sorted(map(tuple, r.groupBy("item").count().collect()))
    assert counts(rows) == counts(again.rows)


def test_functions(spark):
    df = spark.createDataFrame([(["a", "b"], ["b"]), (["a"], ["b"]), (["a"], [])], "items array<string>, wanted array<string>")
    assert [r[0] for r in df.select(fn.contains_all(df["items"], df["wanted"])).collect()] == [True, False, True]
    assert spark.range(1).selectExpr("cast('ab' as binary) as x").select(fn.tidset_and("x", "x")).first()[0] == b"ab"


def test_stream_equals_batch(spark, sf):
    found = windows.run_available(windows.deduplicated(windows.source(spark, sf)), "test-dedup")
    events = b.table(spark, sf, "events")
    assert found.count() == events.selectExpr("user_id", "event_type", "date_trunc('hour', ts)").distinct().count()


@pytest.mark.parametrize("view", sorted(b.VIEWS))
def test_views_are_distinct(spark, sf, view):
    rows = b.VIEWS[view](spark, sf).rows
    assert rows.count() == rows.distinct().count() > 0


def test_explain(spark, sf):
    assert "least count" in plan.explain_mining(b.order_brands(spark, sf), min_support="0.02")
