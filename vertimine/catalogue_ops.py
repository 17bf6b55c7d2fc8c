"""Queries that show one relational, scalar, function or streaming operator each, with its SQL."""

from __future__ import annotations

from pyspark.sql import Window as W
from pyspark.sql import functions as F

from vertimine import catalogue as c
from vertimine.functions import itemset as fn
from vertimine.operators import encode, items, pairs
from vertimine.operators.bottomup import as_text
from vertimine.plans import mine as plan
from vertimine.plans import sqltext as q
from vertimine.sources import baskets as b
from vertimine.streaming import windows as st

add, table = c.add, b.table
OB = b.VIEW_SQL["order_brands"]

add(
    "op_scan_prune_filter",
    lambda s, d: table(s, d, "lineitem").where((F.col("l_shipdate") >= "1995-01-01") & (F.col("l_shipdate") < "1996-01-01")).groupBy("l_suppkey").agg(F.count_distinct("l_orderkey").alias("orders")),
    "SELECT l_suppkey, count(DISTINCT l_orderkey) AS orders FROM lineitem WHERE l_shipdate >= TIMESTAMP '1995-01-01' AND l_shipdate < TIMESTAMP '1996-01-01' GROUP BY 1",
)


def _text_round_trip(s, d):
    path = st.shared(s, "lines")
    b.write_lines(b.order_brands(s, d).rows, path)
    return items.counts(b.read_lines(s, path).rows)


add("op_text_roundtrip", _text_round_trip, f"WITH v AS ({OB}), w AS (SELECT tid, unnest(string_split(string_agg(item, ' '), ' ')) AS item FROM v GROUP BY tid) SELECT item, count(DISTINCT tid) AS support FROM w GROUP BY item")


def _file_round_trip(kind):
    def run(s, d):
        path = st.shared(s, kind)
        found = as_text(plan.mine(b.order_brands(s, d), "filtered_mod", "0.02"))
        found.write.format(kind).partitionBy("k").mode("overwrite").option("header", "true").save(path)
        return s.read.format(kind).option("header", "true").schema("itemset string, support bigint, k int").load(path).select("itemset", "k", "support")

    return run


for _kind in ("parquet", "orc", "json", "csv"):
    add(f"op_sink_{_kind}", _file_round_trip(_kind), q.frequent("order_brands", "0.02"))
add("op_from_columns", lambda s, d: items.counts(b.part_attrs(s, d).rows), f"SELECT item, count(*) AS support FROM ({b.VIEW_SQL['part_attrs']}) GROUP BY item")
add("op_json_items", lambda s, d: items.counts(b.user_keys(s, d).rows), f"SELECT item, count(*) AS support FROM ({b.VIEW_SQL['user_keys']}) GROUP BY item")
add("op_regex_tokens", lambda s, d: items.counts(b.page_words(s, d).rows, 5), f"SELECT item, count(*) AS support FROM ({b.VIEW_SQL['page_words']}) GROUP BY item HAVING count(*) >= 5")
add("op_inner_broadcast", lambda s, d: items.counts(b.order_brands(s, d).rows), f"SELECT item, count(*) AS support FROM ({OB}) GROUP BY item")


def _merge(hint):
    def run(s, d):
        line = table(s, d, "lineitem").select("l_orderkey", "l_suppkey")
        orders = table(s, d, "orders").select("o_orderkey", "o_custkey").hint(hint)
        return line.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_custkey").agg(F.count_distinct("l_suppkey").alias("suppliers"))

    return run


_merged = "SELECT o_custkey, count(DISTINCT l_suppkey) AS suppliers FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1"
add("op_sort_merge", _merge("merge"), _merged)
add("op_shuffle_hash", _merge("shuffle_hash"), _merged)
_rare = f"WITH v AS ({b.VIEW_SQL['order_parts']}), f AS (SELECT item FROM v GROUP BY item HAVING count(*) >= 30)"
add("op_left_semi", lambda s, d: (tx := b.order_parts(s, d)).rows.join(items.counts(tx.rows, 30), "item", "left_semi").groupBy("item").agg(F.max("tid").alias("last")), f"{_rare} SELECT item, max(tid) AS last FROM v WHERE item IN (SELECT item FROM f) GROUP BY item")
add("op_left_anti", lambda s, d: (tx := b.order_parts(s, d)).rows.join(items.counts(tx.rows, 30), "item", "left_anti").groupBy("item").agg(F.max("tid").alias("last")), f"{_rare} SELECT item, max(tid) AS last FROM v WHERE item NOT IN (SELECT item FROM f) GROUP BY item")
add(
    "op_outer_join",
    lambda s, d: table(s, d, "orders").select("o_orderkey").join(table(s, d, "lineitem").select("l_orderkey").distinct(), F.col("o_orderkey") == F.col("l_orderkey"), "full_outer").agg(
        F.count(F.lit(1)).alias("all_rows"), F.sum(F.col("l_orderkey").isNull().cast("bigint")).alias("without_lines"), F.sum(F.col("o_orderkey").isNull().cast("bigint")).alias("without_order")),
    "SELECT count(*) AS all_rows, CAST(count(*) FILTER (WHERE l_orderkey IS NULL) AS BIGINT) AS without_lines, CAST(count(*) FILTER (WHERE o_orderkey IS NULL) AS BIGINT) AS without_order FROM orders FULL JOIN (SELECT DISTINCT l_orderkey FROM lineitem) ON o_orderkey = l_orderkey",
)
add(
    "op_theta_self",
    lambda s, d: (r := b.user_day_types(s, d).rows).alias("a").join(r.alias("b"), (F.col("a.tid") == F.col("b.tid")) & (F.col("a.item") < F.col("b.item"))).groupBy(F.col("a.item").alias("i"), F.col("b.item").alias("j")).agg(F.count(F.lit(1)).alias("support")),
    f"WITH v AS ({b.VIEW_SQL['user_day_types']}) SELECT a.item AS i, b.item AS j, count(*) AS support FROM v a JOIN v b ON a.tid = b.tid AND a.item < b.item GROUP BY 1, 2",
)
add(
    "op_containment_join",
    lambda s, d: b.to_arrays(b.user_day_types(s, d).rows).join(F.broadcast(plan.mine(b.user_day_types(s, d), "filtered_mod", "0.05").select(F.col("items").alias("wanted"))), fn.contains_all(F.col("items"), F.col("wanted"))).groupBy(F.array_join("wanted", "|").alias("itemset")).agg(F.count(F.lit(1)).alias("support")),
    f"{q.itemsets('user_day_types', '0.05')} SELECT {q.TEXT} AS itemset, support FROM f",
)


def _interval(s, d):
    """Range join in time by bucket: an event is dealt to its hour and the next, so that only neighbouring hours meet."""
    e = table(s, d, "events").select("user_id", "event_type", F.unix_micros(F.col("ts").cast("timestamp")).alias("t"))
    hour = 3_600_000_000
    bad = e.where("event_type = 'error'").select("user_id", F.col("t").alias("t0"), F.explode(F.array(F.floor(F.col("t") / hour), F.floor(F.col("t") / hour) + 1)).alias("h"))
    near = e.withColumn("h", F.floor(F.col("t") / hour)).join(bad, ["user_id", "h"]).where((F.col("t") >= F.col("t0")) & (F.col("t") <= F.col("t0") + hour))
    return near.groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))


add("op_interval_join", _interval, "SELECT e.event_type, count(*) AS n FROM events e JOIN events x ON x.event_type = 'error' AND e.user_id = x.user_id AND e.ts >= x.ts AND e.ts <= x.ts + INTERVAL 1 HOUR GROUP BY 1")


def _as_of(s, d):
    """Latest earlier purchase of the same user by a running last value: one sort, no join."""
    w = W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(W.unboundedPreceding, -1)
    e = table(s, d, "events").withColumn("bought", F.last(F.when(F.col("event_type") == "purchase", F.col("event_id")), True).over(w))
    return e.where("bought is not null").select("event_id", "bought")


add("op_asof_join", _as_of, "SELECT event_id, bought FROM (SELECT event_id, last_value(CASE WHEN event_type = 'purchase' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS bought FROM events) WHERE bought IS NOT NULL")
add("op_count_distinct", lambda s, d: b.customer_parts(s, d).rows.agg(F.count_distinct("tid").alias("transactions"), F.count_distinct("item").alias("items")), f"SELECT count(DISTINCT tid) AS transactions, count(DISTINCT item) AS items FROM ({b.VIEW_SQL['customer_parts']})")
add("op_approx_distinct", lambda s, d: b.customer_parts(s, d).rows.agg(F.approx_count_distinct("item").alias("items")))
add("op_collect_sorted", lambda s, d: b.to_arrays(b.order_brands(s, d).rows).select("tid", F.array_join("items", "|").alias("items")), f"SELECT tid, string_agg(item, '|' ORDER BY item) AS items FROM ({OB}) GROUP BY tid")
_sets = c._sets("order_brands", "0.02")
_by = "count(*) AS n, CAST(sum(support) AS BIGINT) AS support FROM (SELECT k, items[1] AS first, support FROM f)"


def _multi(kind):
    def run(s, d):
        x = _sets(s, d).select(F.col("k").cast("int").alias("k"), F.col("items")[0].alias("first"), "support")
        g = {"cube": lambda: x.cube("k", "first"), "rollup": lambda: x.rollup("k", "first"), "sets": lambda: x.groupingSets([["k"], ["first"], []], "k", "first")}[kind]()
        return g.agg(F.count(F.lit(1)).alias("n"), F.sum("support").alias("support"))

    return run


for _kind, _group in (("cube", "CUBE (k, first)"), ("rollup", "ROLLUP (k, first)"), ("sets", "GROUPING SETS ((k), (first), ())")):
    add(f"op_grouping_{_kind}", _multi(_kind), f"{q.itemsets('order_brands', '0.02')} SELECT k, first, {_by} GROUP BY {_group}")
add("op_having_minsup", lambda s, d: pairs.count_sparse(encode.full(b.user_day_keys(s, d).rows), 5, "items"), f"WITH v AS MATERIALIZED ({b.VIEW_SQL['user_day_keys']}) SELECT a.item AS i, b.item AS j, count(*) AS support FROM v a JOIN v b ON a.tid = b.tid AND a.item < b.item GROUP BY 1, 2 HAVING count(*) >= 5")
_counted = f"SELECT item, count(*) AS support FROM ({b.VIEW_SQL['user_day_keys']}) GROUP BY item"


def _ranked(name, f, sql):
    add(name, lambda s, d: items.counts(b.user_day_keys(s, d).rows).withColumn("place", f().over(W.orderBy("support", "item") if name != "op_dense_rank" else W.orderBy("support")).cast("int")), f"SELECT item, support, CAST({sql} AS INT) AS place FROM ({_counted})")


_ranked("op_rank_items", F.row_number, "row_number() OVER (ORDER BY support, item)")
_ranked("op_dense_rank", F.dense_rank, "dense_rank() OVER (ORDER BY support)")
_ranked("op_ntile", lambda: F.ntile(4), "ntile(4) OVER (ORDER BY support, item)")
add(
    "op_running_share",
    lambda s, d: items.counts(b.user_day_keys(s, d).rows).withColumn("running", F.sum("support").over(W.orderBy("support", "item").rowsBetween(W.unboundedPreceding, 0))),
    f"SELECT item, support, CAST(sum(support) OVER (ORDER BY support, item ROWS UNBOUNDED PRECEDING) AS BIGINT) AS running FROM ({_counted})",
)
add(
    "op_range_frame",
    lambda s, d: table(s, d, "events").select("event_id", F.size(F.collect_set("event_type").over(W.partitionBy("user_id").orderBy(F.unix_micros(F.col("ts").cast("timestamp"))).rangeBetween(-3_600_000_000, 0))).cast("bigint").alias("types")),
    "SELECT event_id, len(list_distinct(list(event_type) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 HOUR PRECEDING AND CURRENT ROW))) AS types FROM events",
)
add(
    "op_lag_gap",
    lambda s, d: table(s, d, "events").withColumn("new", (F.unix_micros(F.col("ts").cast("timestamp")) - F.coalesce(F.lag(F.unix_micros(F.col("ts").cast("timestamp"))).over(W.partitionBy("user_id").orderBy("ts", "event_id")), F.lit(0)) > 1_800_000_000).cast("bigint")).groupBy("user_id").agg(F.sum("new").alias("sessions")),
    "SELECT user_id, CAST(sum(CASE WHEN p IS NULL OR epoch_us(ts) - epoch_us(p) > 1800000000 THEN 1 ELSE 0 END) AS BIGINT) AS sessions FROM (SELECT user_id, ts, lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS p FROM events) GROUP BY 1",
)
add("op_sort_limit", lambda s, d: as_text(_sets(s, d)).orderBy(F.col("support").desc(), "itemset").limit(20), f"{q.frequent('order_brands', '0.02')} ORDER BY support DESC, itemset LIMIT 20")
_a, _b = "order_brands", ("0.02", "0.022")


def _set_op(kind):
    def run(s, d):
        x, y = (as_text(plan.mine(b.order_brands(s, d), "filtered_mod", t)).select("itemset") for t in _b)
        return {"union": lambda: x.union(y).distinct(), "intersect": lambda: x.intersect(y), "except": lambda: x.exceptAll(y)}[kind]()

    return run


for _kind in ("union", "intersect", "except"):
    add(f"op_{_kind}", _set_op(_kind), f"SELECT itemset FROM ({q.frequent(_a, _b[0])}) {_kind} SELECT itemset FROM ({q.frequent(_a, _b[1])})")
add("op_string_fns", lambda s, d: table(s, d, "part").select("p_partkey", F.concat_ws("=", F.lit("b"), F.upper("p_brand")).alias("tag"), F.length("p_name").cast("bigint").alias("n"), F.substring("p_type", 1, 3).alias("lead")), "SELECT p_partkey, 'b=' || upper(p_brand) AS tag, length(p_name) AS n, substr(p_type, 1, 3) AS lead FROM part")
add("op_date_fns", lambda s, d: table(s, d, "orders").groupBy(F.year("o_orderdate").cast("bigint").alias("y"), F.month("o_orderdate").cast("bigint").alias("m")).agg(F.max(F.datediff(F.last_day("o_orderdate"), F.to_date("o_orderdate"))).cast("bigint").alias("left")), "SELECT year(o_orderdate) AS y, month(o_orderdate) AS m, CAST(max(date_diff('day', CAST(o_orderdate AS DATE), last_day(o_orderdate))) AS BIGINT) AS \"left\" FROM orders GROUP BY 1, 2")
add("op_math_fns", lambda s, d: table(s, d, "lineitem").groupBy(F.pmod(F.col("l_orderkey"), F.lit(7)).alias("m")).agg(F.sum(F.ceil(F.col("l_quantity") / 7)).alias("up"), F.sum(F.floor(F.col("l_quantity") / 7)).alias("down")), "SELECT l_orderkey % 7 AS m, CAST(sum(ceil(l_quantity / 7)) AS BIGINT) AS up, CAST(sum(floor(l_quantity / 7)) AS BIGINT) AS down FROM lineitem GROUP BY 1")
_arrays = f"SELECT tid, list(item ORDER BY item) AS items FROM ({OB}) GROUP BY tid"
add("op_array_fns", lambda s, d: b.to_arrays(b.order_brands(s, d).rows).select("tid", F.array_join(F.slice("items", 2, 3), "|").alias("mid"), F.size("items").cast("bigint").alias("n")), f"SELECT tid, array_to_string(items[2:4], '|') AS mid, len(items) AS n FROM ({_arrays})")
add("op_higher_order", lambda s, d: b.to_arrays(b.order_brands(s, d).rows).select("tid", F.array_join(F.transform(F.filter("items", lambda x: x > "Brand#2"), F.upper), "|").alias("late")), f"SELECT tid, array_to_string(list_transform(list_filter(items, lambda x: x > 'Brand#2'), lambda x: upper(x)), '|') AS late FROM ({_arrays})")
add("op_map_fns", lambda s, d: b.to_arrays(b.order_brands(s, d).rows).select("tid", F.element_at(F.map_from_arrays("items", F.sequence(F.lit(1), F.size("items"))), F.element_at("items", -1)).cast("bigint").alias("last")), f"SELECT tid, len(items) AS last FROM ({_arrays})")
add(
    "op_bitmap_support",
    lambda s, d: b.order_brands(s, d).rows.groupBy("item", F.bitmap_bucket_number("tid").alias("bucket")).agg(F.bitmap_count(F.bitmap_construct_agg(F.bitmap_bit_position("tid"))).alias("n")).groupBy("item").agg(F.sum("n").alias("support")),
    f"SELECT item, count(*) AS support FROM ({OB}) GROUP BY item",
)
add(
    "op_pivot_matrix",
    lambda s, d: pairs.count_sparse(encode.full(b.user_day_types(s, d).rows), 1, "items").groupBy("i").pivot("j", ["error", "login", "purchase", "view"]).sum("support"),
    f"WITH v AS MATERIALIZED ({b.VIEW_SQL['user_day_types']}), p AS (SELECT a.item AS i, b.item AS j FROM v a JOIN v b ON a.tid = b.tid AND a.item < b.item) SELECT i, " + ", ".join(f"nullif(count(*) FILTER (WHERE j = '{x}'), 0) AS \"{x}\"" for x in ("error", "login", "purchase", "view")) + " FROM p GROUP BY i",
)


def _udf_strip(s, d):
    tx = b.order_brands(s, d)
    ranked = items.rank(items.counts(tx.rows, c.least(tx, "0.02")))
    known = {r["item"]: r["rank"] for r in ranked.collect()}
    return b.to_arrays(tx.rows).select("tid", F.array_join(fn.strip_udf(known)("items"), ",").alias("ranks")).where("ranks <> ''")


add("op_udf_strip", _udf_strip, c.SQL["strip_tx_order_brands"])
add("op_arrow_strip", lambda s, d: encode.strip_arrays(b.to_arrays((tx := b.order_brands(s, d)).rows), {r["item"]: r["rank"] for r in items.rank(items.counts(tx.rows, c.least(tx, "0.02"))).collect()}).select("tid", F.array_join("ranks", ",").alias("ranks")), c.SQL["strip_tx_order_brands"])
add("op_udaf_tidset", lambda s, d: b.order_brands(s, d).rows.groupBy("item").agg(fn.tidset_count("tid").alias("support")), f"SELECT item, count(*) AS support FROM ({OB}) GROUP BY item")


def _udtf(s, d):
    fn.register(s)
    tx = b.user_day_types(s, d)
    tx.rows.createOrReplaceTempView("user_day_rows")
    return s.sql(f"SELECT * FROM frequent_itemsets(TABLE(SELECT tid, item FROM user_day_rows) WITH SINGLE PARTITION, {c.least(tx, '0.05')})")


add("op_udtf_mine", _udtf, q.frequent("user_day_types", "0.05"))


def _udtf_classes(s, d):
    """Classes by SQL: every item with the later items of its transactions; each class mined by the table function."""
    fn.register(s)
    rows = b.user_day_types(s, d).rows
    rows.alias("a").join(rows.alias("b"), (F.col("a.tid") == F.col("b.tid")) & (F.col("a.item") < F.col("b.item"))).select(F.col("a.item").alias("prefix"), F.col("b.item").alias("member"), F.col("a.tid").alias("tid")).createOrReplaceTempView("class_rows")
    least = c.least(b.user_day_types(s, d), "0.05")
    return s.sql(f"SELECT itemset, k, support FROM mine_class(least => {least}, row => TABLE(SELECT prefix, member, tid FROM class_rows) PARTITION BY prefix)")


add("op_udtf_classes", _udtf_classes, f"{q.frequent('user_day_types', '0.05')} WHERE k > 1")


def _tidset_and(s, d):
    """Support of pairs by the bitwise and of bitmaps, bucket by bucket."""
    rows = b.user_day_types(s, d).rows
    maps = rows.groupBy("item", F.bitmap_bucket_number("tid").alias("bucket")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("tid")).alias("m"))
    two = maps.alias("a").join(maps.alias("b"), (F.col("a.bucket") == F.col("b.bucket")) & (F.col("a.item") < F.col("b.item")))
    return two.groupBy(F.col("a.item").alias("i"), F.col("b.item").alias("j")).agg(F.sum(F.bitmap_count(fn.tidset_and(F.col("a.m"), F.col("b.m")))).alias("support"))


add("op_udf_tidset_and", _tidset_and, c.SQL["op_theta_self"])


def _segments(s, d):
    """Per market segment: itemsets frequent against the segment's own number of customers."""
    segment = table(s, d, "customer").select(F.col("c_custkey").alias("tid"), "c_mktsegment")
    rows = b.customer_brands(s, d).rows.join(segment, "tid")
    size = rows.groupBy("c_mktsegment").agg(F.count_distinct("tid").alias("n"))
    counted = rows.groupBy("c_mktsegment", "item").agg(F.count(F.lit(1)).alias("support"))
    return counted.join(F.broadcast(size), "c_mktsegment").where(F.col("support") * 10 >= F.col("n") * 8).select("c_mktsegment", "item", "support")


add("op_segment_mining", _segments, f"WITH v AS (SELECT v.*, c_mktsegment FROM ({b.VIEW_SQL['customer_brands']}) v JOIN customer ON tid = c_custkey), n AS (SELECT c_mktsegment, count(DISTINCT tid) AS n FROM v GROUP BY 1) SELECT c_mktsegment, item, count(*) AS support FROM v JOIN n USING (c_mktsegment) GROUP BY c_mktsegment, item, n HAVING count(*) * 10 >= n * 8")
add(
    "op_constraint_mining",
    lambda s, d: as_text((x := plan.mine(b.turn_words(s, d), "auto", "0.2", max_len=4)).where(F.array_contains("items", x.where("k = 1").orderBy(F.col("support").desc(), F.col("items")[0]).first()["items"][0]) & F.col("k").between(2, 4))),
    f"{q.itemsets('turn_words', '0.2')}, t AS (SELECT items[1] AS top FROM f WHERE k = 1 ORDER BY support DESC, items[1] LIMIT 1) SELECT {q.TEXT} AS itemset, k, support FROM f, t WHERE list_contains(items, top) AND k BETWEEN 2 AND 4",
)
add("op_view_sql", lambda s, d: (table(s, d, "events").createOrReplaceTempView("events_v"), s.sql("SELECT event_type, count(*) AS n FROM events_v GROUP BY event_type"))[1], "SELECT event_type, count(*) AS n FROM events GROUP BY event_type")


# Streams, drained once; a last watermark holds back windows that are still open, so append mode leaves those out.
_open = "(SELECT max(ts) - INTERVAL 1 HOUR FROM events)"
_days = "SELECT user_id, time_bucket(INTERVAL 1 DAY, ts) AS start, event_type FROM events"


def _stream(make, name, mode="append"):
    return lambda s, d: st.run_available(make(st.source(s, d)), name, mode)


add("stream_tumbling", _stream(st.tumbling, "tumbling"), f"SELECT user_id, start, string_agg(DISTINCT event_type, '|' ORDER BY event_type) AS items FROM ({_days}) WHERE start + INTERVAL 1 DAY <= {_open} GROUP BY 1, 2")
add(
    "stream_sliding",
    _stream(st.sliding, "sliding"),
    f"SELECT event_type, start, count(*) AS n FROM (SELECT event_type, time_bucket(INTERVAL 1 DAY, ts) - to_days(CAST(k AS INT)) AS start FROM events, range(2) t(k)) WHERE start + INTERVAL 2 DAY <= {_open} GROUP BY 1, 2",
)
add(
    "stream_session",
    _stream(st.session, "session"),
    f"""WITH e AS (SELECT *, CASE WHEN ts - lag(ts) OVER w < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)),
g AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS g FROM e)
SELECT user_id, min(ts) AS start, count(*) AS n, string_agg(DISTINCT event_type, '|' ORDER BY event_type) AS items FROM g GROUP BY user_id, g HAVING max(ts) + INTERVAL 30 MINUTE <= {_open}""",
)
add("stream_dedup", _stream(st.deduplicated, "dedup"), "SELECT DISTINCT user_id, event_type, date_trunc('hour', ts) AS hour FROM events")
add(
    "stream_pairs",
    lambda s, d: st.run_available(st.pair_counts(st.source(s, d)), "pairs").groupBy("start", "i", "j").agg(F.count(F.lit(1)).alias("users")),
    f"WITH x AS (SELECT DISTINCT user_id, start, event_type FROM ({_days}) WHERE start + INTERVAL 1 DAY <= {_open}) SELECT a.start, a.event_type AS i, b.event_type AS j, count(*) AS users FROM x a JOIN x b ON a.user_id = b.user_id AND a.start = b.start AND a.event_type < b.event_type GROUP BY 1, 2, 3",
)


def _stream_late(s, d):
    """Events in four files by time, the second file coming last: rows older than the watermark are dropped, all others counted."""
    path = st.shared(s, "late-input")
    events = table(s, d, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", "event_type")
    quarter = F.ntile(4).over(W.orderBy("ts", "event_id"))
    events = events.withColumn("quarter", quarter).persist()
    for n, part in enumerate((1, 3, 4, 2)):
        events.where(F.col("quarter") == part).drop("quarter").coalesce(1).write.mode("overwrite").parquet(f"{path}/in{n}")
    stream = s.readStream.schema("event_id bigint, ts timestamp, user_id bigint, event_type string").option("maxFilesPerTrigger", 1).parquet(f"{path}/in*")
    return st.run_available(st.sliding(stream, "1 day", "1 day"), "late")


add(
    "stream_late",
    _stream_late,
    f"""WITH e AS (SELECT *, ntile(4) OVER (ORDER BY ts, event_id) AS q FROM events), k AS (SELECT * FROM e WHERE q <> 2)
SELECT event_type, time_bucket(INTERVAL 1 DAY, ts) AS start, count(*) AS n FROM k WHERE time_bucket(INTERVAL 1 DAY, ts) + INTERVAL 1 DAY <= {_open} GROUP BY 1, 2""",
)


def _stream_mine(s, d):
    path = st.shared(s, "mined")
    st_query = st.tumbling(st.source(s, d)).writeStream.outputMode("append").trigger(availableNow=True).option("checkpointLocation", f"{path}/state")
    st_query.foreachBatch(st.mine_windows(20, f"{path}/data")).start().awaitTermination()
    return s.read.parquet(f"{path}/data").select("itemset", "k", "support")


add(
    "stream_mine",
    _stream_mine,
    q.frequent("user_day_types", min_count=20, source=f"SELECT DISTINCT user_id || ' ' || start AS tid, event_type AS item FROM ({_days}) WHERE start + INTERVAL 1 DAY <= {_open}"),
)


def _stream_state(s, d):
    """Arbitrary state per user, drained once; the last update of each user and type counts."""
    out = st.run_available(st.decayed_counts(st.source(s, d)), "decayed", "update")
    # Of all updates of a user and type the last counts; among those of one moment, the one with most events in it, which weighs most.
    last = out.groupBy("user_id", "event_type").agg(F.max(F.struct("as_of", "weight")).alias("last"))
    return last.select("user_id", "event_type", F.round("last.weight", 6).alias("weight"))


def _decayed_batch(s, d):
    """The decayed counts by plain aggregation: each event weighs 0.5 ** (days to the user's last event of the type / 7)."""
    e = table(s, d, "events").select("user_id", "event_type", (F.unix_micros(F.col("ts").cast("timestamp")) / 86_400_000_000).alias("day"))
    last = F.max("day").over(W.partitionBy("user_id", "event_type"))
    return e.withColumn("last", last).groupBy("user_id", "event_type").agg(F.round(F.sum(F.pow(F.lit(0.5), (F.col("last") - F.col("day")) / 7)), 6).alias("weight"))


_decayed_sql = "SELECT user_id, event_type, round(sum(power(0.5, (l - t) / 7)), 6) AS weight FROM (SELECT user_id, event_type, epoch_us(ts) / 86400000000 AS t, max(epoch_us(ts) / 86400000000) OVER (PARTITION BY user_id, event_type) AS l FROM events) GROUP BY 1, 2"
add("op_decayed_counts", _decayed_batch, _decayed_sql)
add("stream_state", _stream_state, _decayed_sql)
