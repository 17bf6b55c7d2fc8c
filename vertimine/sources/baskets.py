"""Transactions from the given tables.

A view yields distinct (tid, item) rows and the number of transactions, which counts transactions without items too.
Items are strings; null items are dropped, repeated ones count once. Beside each view stands the same in DuckDB SQL.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Letters a-z and U+00E0 to U+00FF make words.
NOT_WORD = "[^a-zà-ÿ]+"


@dataclass(frozen=True)
class Transactions:
    """rows: distinct (tid, item); transactions: one row per transaction, or None if every transaction has an item; lists: (tid, items), where
    a source has them so, with one row a tid (items distinct) or with several (then `whole` is False)."""

    rows: DataFrame
    transactions: DataFrame | None = None
    lists: DataFrame | None = None
    whole: bool = False

    def arrays(self) -> DataFrame:
        """(tid, items): transactions that have items. No shuffle where the source has whole lists, else one, by tid."""
        if self.lists is None:
            return to_arrays(self.rows)
        have = self.lists.where(F.size("items") > 0)
        if self.whole:
            return have
        return have.groupBy("tid").agg(F.array_distinct(F.flatten(F.collect_list("items"))).alias("items"))

    def count(self) -> int:
        if self.transactions is not None:
            return self.transactions.count()
        return self.rows.agg(F.count_distinct("tid").alias("n")).first()["n"]

    @classmethod
    def of(cls, rows: DataFrame, transactions: DataFrame | None = None) -> Transactions:
        known = rows.where("tid is not null and item is not null")
        return cls(known.distinct(), transactions, known.groupBy("tid").agg(F.collect_set("item").alias("items")), True)

    @classmethod
    def from_arrays(cls, frame: DataFrame, tid: str = "tid", items: str = "items") -> Transactions:
        return cls.of(frame.select(F.col(tid).alias("tid"), F.explode(items).alias("item")), frame.select(F.col(tid).alias("tid")))


def to_arrays(rows: DataFrame) -> DataFrame:
    """(tid, item) rows to (tid, items) with sorted items."""
    return rows.groupBy("tid").agg(F.sort_array(F.collect_list("item")).alias("items"))


def from_columns(frame: DataFrame, items: dict[str, Column], tid: Column | None = None) -> DataFrame:
    """Wide rows to transactions: one `name=value` item per column; rows without a key get a generated tid.

    The tid is drawn in a projection of its own, below the explode, so that the items of a row share it.
    """
    tagged = F.array(*[F.concat(F.lit(f"{k}="), c.cast("string")) for k, c in items.items()])
    rows = frame.select((tid if tid is not None else F.monotonically_increasing_id()).alias("tid"), tagged.alias("_items"))
    return rows.select("tid", F.explode("_items").alias("item"))


def wide(frame: DataFrame, items: dict[str, Column], tid: Column | None = None) -> Transactions:
    """from_columns as transactions. Items carry their column's name, so a row has each once and nothing need be made distinct; `tid` must be unique."""
    rows = from_columns(frame, items, tid)
    tagged = F.array(*[F.concat(F.lit(f"{k}="), c.cast("string")) for k, c in items.items()])
    lists = frame.select((tid if tid is not None else F.monotonically_increasing_id()).alias("tid"), F.filter(tagged, lambda x: x.isNotNull()).alias("items"))
    return Transactions(rows.where("item is not null"), frame.select(F.lit(1).alias("tid")), lists, True)


def words(text: Column) -> Column:
    return F.filter(F.split(F.lower(text), NOT_WORD), lambda w: w != "")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_lines(spark: SparkSession, path: str) -> Transactions:
    """Text, one transaction a line, items parted by white space; the tid is generated."""
    lines = spark.read.text(path).select(F.monotonically_increasing_id().alias("tid"), F.filter(F.split("value", r"\s+"), lambda x: x != "").alias("items"))
    return Transactions.from_arrays(lines)


def write_lines(rows: DataFrame, path: str) -> None:
    to_arrays(rows).select(F.array_join("items", " ").alias("value")).write.mode("overwrite").text(path)


def write_itemsets(itemsets: DataFrame, path: str) -> None:
    """Text, one itemset a line: its items parted by blanks, a tab, its support. Items must hold neither."""
    itemsets.select(F.concat_ws("\t", F.array_join("items", " "), F.col("support").cast("string")).alias("value")).write.mode("overwrite").text(path)


def read_itemsets(spark: SparkSession, path: str) -> DataFrame:
    parts = F.split("value", "\t")
    return spark.read.text(path).select(F.split(parts[0], " ").alias("items"), parts[1].cast("bigint").alias("support")).select("items", F.size("items").alias("k"), "support")


def _line(spark, d):
    return table(spark, d, "lineitem")


def order_parts(spark, d):
    return Transactions.of(_line(spark, d).select(F.col("l_orderkey").alias("tid"), F.col("l_partkey").cast("string").alias("item")))


def order_suppliers(spark, d):
    return Transactions.of(_line(spark, d).select(F.col("l_orderkey").alias("tid"), F.col("l_suppkey").cast("string").alias("item")))


def order_brands(spark, d):
    part = table(spark, d, "part").select("p_partkey", "p_brand")
    return Transactions.of(_line(spark, d).join(part, F.col("l_partkey") == F.col("p_partkey")).select(F.col("l_orderkey").alias("tid"), F.col("p_brand").alias("item")))


def _customer(spark, d, item):
    orders = table(spark, d, "orders").select("o_orderkey", "o_custkey")
    return _line(spark, d).join(orders, F.col("l_orderkey") == F.col("o_orderkey")).select(F.col("o_custkey").alias("tid"), item)


def customer_parts(spark, d):
    return Transactions.of(_customer(spark, d, F.col("l_partkey").cast("string").alias("item")))


def customer_suppliers(spark, d):
    return Transactions.of(_customer(spark, d, F.col("l_suppkey").cast("string").alias("item")))


def customer_brands(spark, d):
    part = table(spark, d, "part").select("p_partkey", "p_brand")
    return Transactions.of(_customer(spark, d, F.col("l_partkey")).join(part, F.col("l_partkey") == F.col("p_partkey")).select("tid", F.col("p_brand").alias("item")))


def line_attrs(spark, d):
    items = {
        "rf": F.col("l_returnflag"), "ls": F.col("l_linestatus"), "ln": F.col("l_linenumber"), "q": F.floor((F.col("l_quantity") - 1) / 10).cast("int"),
        "d": F.round(F.col("l_discount") * 100).cast("int"), "t": F.round(F.col("l_tax") * 100).cast("int"), "y": F.year("l_shipdate"),
    }
    return wide(_line(spark, d), items)


def line_bins(spark, d):
    orders = table(spark, d, "orders").select("o_orderkey", "o_orderstatus", "o_orderpriority", "o_totalprice")

    def flag(c: Column) -> Column:
        return c.cast("int")

    items = {
        "rf": F.col("l_returnflag"), "ls": F.col("l_linestatus"), "ln": flag(F.col("l_linenumber") > 3), "q": flag(F.col("l_quantity") > 25),
        "d": flag(F.round(F.col("l_discount") * 100) > 5), "t": flag(F.round(F.col("l_tax") * 100) > 4), "p": flag(F.col("l_extendedprice") > 50000),
        "os": F.col("o_orderstatus"), "op": flag(F.col("o_orderpriority") < "3"), "tp": flag(F.col("o_totalprice") > 250000),
    }
    return wide(_line(spark, d).join(orders, F.col("l_orderkey") == F.col("o_orderkey")), items)


def part_attrs(spark, d):
    name = F.split("p_name", " ")
    items = {"b": F.col("p_brand"), "ty": F.col("p_type"), "sz": F.floor(F.col("p_size") / 10).cast("int"), "w1": F.get(name, 0), "w2": F.get(name, 1)}
    return wide(table(spark, d, "part"), items, F.col("p_partkey"))


def _user_day():
    return (F.col("user_id") * 100000 + F.datediff(F.to_date("ts"), F.lit("1970-01-01"))).alias("tid")


def user_day_types(spark, d):
    return Transactions.of(table(spark, d, "events").select(_user_day(), F.col("event_type").alias("item")))


def user_day_keys(spark, d):
    k = F.floor(F.get_json_object("props", "$.k").cast("int") / 10).cast("string")
    return Transactions.of(table(spark, d, "events").select(_user_day(), F.concat("event_type", F.lit(":"), k).alias("item")))


def user_keys(spark, d):
    return Transactions.of(table(spark, d, "events").select(F.col("user_id").alias("tid"), F.get_json_object("props", "$.k").alias("item")))


def _words(frame: DataFrame, tid: Column, text: Column) -> Transactions:
    found = frame.select(tid.alias("tid"), F.array_distinct(F.coalesce(words(text), F.array())).alias("items")).where("tid is not null")
    rows = found.select("tid", F.explode("items").alias("item")).where("item is not null").distinct()
    return Transactions(rows, frame.select(tid.alias("tid")), found)


def doc_words(spark, d):
    return _words(table(spark, d, "documents"), F.col("doc_id"), F.col("text"))


def page_words(spark, d):
    return _words(table(spark, d, "pages"), F.col("page_id"), F.regexp_replace("html", "<[^>]*>", " "))


def turn_words(spark, d):
    return _words(table(spark, d, "conversations"), F.col("conv_id") * 1000 + F.col("turn"), F.col("text"))


VIEWS: dict[str, Callable[[SparkSession, str], Transactions]] = {
    f.__name__: f
    for f in (order_parts, order_suppliers, order_brands, customer_parts, customer_suppliers, customer_brands, line_attrs, line_bins, part_attrs, user_day_types, user_day_keys, user_keys, doc_words, page_words, turn_words)
}

_DAY = "user_id * 100000 + date_diff('day', DATE '1970-01-01', CAST(ts AS DATE))"


def _tagged(items: dict[str, str], tid: str, source: str) -> str:
    listed = ", ".join(f"'{k}=' || CAST({v} AS VARCHAR)" for k, v in items.items())
    return f"SELECT tid, unnest(items) AS item FROM (SELECT {tid} AS tid, [{listed}] AS items FROM {source})"


def _split(source: str, tid: str, text: str) -> str:
    return f"SELECT DISTINCT tid, item FROM (SELECT {tid} AS tid, unnest(regexp_split_to_array(lower({text}), '{NOT_WORD}')) AS item FROM {source}) WHERE item <> ''"


VIEW_SQL: dict[str, str] = {
    "order_parts": "SELECT DISTINCT l_orderkey AS tid, CAST(l_partkey AS VARCHAR) AS item FROM lineitem",
    "order_suppliers": "SELECT DISTINCT l_orderkey AS tid, CAST(l_suppkey AS VARCHAR) AS item FROM lineitem",
    "order_brands": "SELECT DISTINCT l_orderkey AS tid, p_brand AS item FROM lineitem JOIN part ON l_partkey = p_partkey",
    "customer_parts": "SELECT DISTINCT o_custkey AS tid, CAST(l_partkey AS VARCHAR) AS item FROM lineitem JOIN orders ON l_orderkey = o_orderkey",
    "customer_suppliers": "SELECT DISTINCT o_custkey AS tid, CAST(l_suppkey AS VARCHAR) AS item FROM lineitem JOIN orders ON l_orderkey = o_orderkey",
    "customer_brands": "SELECT DISTINCT o_custkey AS tid, p_brand AS item FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey",
    "line_attrs": _tagged(
        {"rf": "l_returnflag", "ls": "l_linestatus", "ln": "l_linenumber", "q": "CAST(floor((l_quantity - 1) / 10) AS INT)", "d": "CAST(round(l_discount * 100) AS INT)", "t": "CAST(round(l_tax * 100) AS INT)", "y": "year(l_shipdate)"},
        "row_number() OVER ()", "lineitem",
    ),
    "line_bins": _tagged(
        {"rf": "l_returnflag", "ls": "l_linestatus", "ln": "CAST(l_linenumber > 3 AS INT)", "q": "CAST(l_quantity > 25 AS INT)", "d": "CAST(round(l_discount * 100) > 5 AS INT)", "t": "CAST(round(l_tax * 100) > 4 AS INT)",
         "p": "CAST(l_extendedprice > 50000 AS INT)", "os": "o_orderstatus", "op": "CAST(o_orderpriority < '3' AS INT)", "tp": "CAST(o_totalprice > 250000 AS INT)"},
        "row_number() OVER ()", "lineitem JOIN orders ON l_orderkey = o_orderkey",
    ),
    "part_attrs": _tagged({"b": "p_brand", "ty": "p_type", "sz": "CAST(floor(p_size / 10) AS INT)", "w1": "split_part(p_name, ' ', 1)", "w2": "split_part(p_name, ' ', 2)"}, "p_partkey", "part"),
    "user_day_types": f"SELECT DISTINCT {_DAY} AS tid, event_type AS item FROM events",
    "user_day_keys": f"SELECT DISTINCT {_DAY} AS tid, event_type || ':' || CAST(CAST(json_extract_string(props, '$.k') AS INT) // 10 AS VARCHAR) AS item FROM events",
    "user_keys": "SELECT DISTINCT user_id AS tid, json_extract_string(props, '$.k') AS item FROM events",
    "doc_words": _split("documents", "doc_id", "text"),
    "page_words": _split("pages", "page_id", "regexp_replace(html, '<[^>]*>', ' ', 'g')"),
    "turn_words": _split("conversations", "conv_id * 1000 + turn", "text"),
}
#: SQL for the number of transactions where it isn't the number of distinct tids.
COUNT_SQL = {"doc_words": "SELECT count(*) FROM documents", "page_words": "SELECT count(*) FROM pages", "turn_words": "SELECT count(*) FROM conversations"}


def replicated(view: Transactions, times: int, stride: int) -> Transactions:
    """The same transactions `times` over under fresh tids (tids are below stride)."""
    copies = F.explode(F.array(*[F.lit(i).cast("bigint") for i in range(times)]))
    rows = view.rows.select("*", copies.alias("_copy")).select((F.col("tid") + F.col("_copy") * stride).alias("tid"), "item")
    tids = None if view.transactions is None else view.transactions.select("*", copies.alias("_copy")).select((F.col("tid") + F.col("_copy") * stride).alias("tid"))
    lists = None if view.lists is None else view.lists.select("*", copies.alias("_copy")).select((F.col("tid") + F.col("_copy") * stride).alias("tid"), "items")
    return Transactions(rows, tids, lists, view.whole)
