"""Queries of the mining engine, each with its SQL where SQL can express it. add() keeps the two together."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vertimine import measures, threshold
from vertimine.operators import classes, encode, items, levelwise, pairs, partitioners, reference, rules, vertical
from vertimine.operators.bottomup import as_text
from vertimine.plans import mine as plan
from vertimine.plans import sqltext as q
from vertimine.sources import baskets as b

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}
P = 10
#: Thresholds at which a view has an answer of a size to compare.
AT = {
    "order_brands": "0.02", "customer_brands": "0.6", "line_attrs": "0.1", "line_bins": "0.2", "user_day_types": "0.05", "turn_words": "0.2",
    "doc_words": "0.4", "user_day_keys": "0.01", "user_keys": "0.4", "part_attrs": "0.02", "order_suppliers": "0.005", "customer_suppliers": "0.3",
    "order_parts": "0.002", "customer_parts": "0.018", "page_words": "0.6",
}


def add(name: str, run: Callable[[SparkSession, str], DataFrame], sql: str | None = None) -> None:
    if name in QUERIES:
        raise ValueError(name)
    QUERIES[name] = run
    if sql is not None:
        SQL[name] = sql


def least(tx: b.Transactions, at: str) -> int:
    return threshold.resolve(tx.count(), at)


def prepared(spark, d, view, at):
    tx = b.VIEWS[view](spark, d)
    prep = plan.prepare(tx, plan.MiningConfig(), at)
    prep.encoded = encode.strip(tx.rows, prep.frequent, prep.n_items).persist()
    return tx, prep


def _view_queries(view: str, at: str) -> None:
    make, sql, n = b.VIEWS[view], b.VIEW_SQL[view], b.COUNT_SQL.get(view, "SELECT count(DISTINCT tid) FROM v")
    add(
        f"profile_{view}",
        lambda s, d: measures.profile(make(s, d)).withColumn("mean_width", F.round("mean_width", 6)),
        f"""WITH v AS MATERIALIZED ({sql}), w AS (SELECT tid, count(*) AS w FROM v GROUP BY tid), n AS (SELECT ({n}) AS n)
SELECT (SELECT n FROM n) AS transactions, (SELECT count(DISTINCT item) FROM v) AS items, CAST(sum(w) AS BIGINT) AS occurrences, max(w) AS max_width,
       round(sum(w) / (SELECT n FROM n), 6) AS mean_width FROM w""",
    )
    add(f"item_support_{view}", lambda s, d: items.counts((tx := make(s, d)).rows, least(tx, at)), f"WITH {q.head(view, at)} SELECT item, support FROM s")
    add(
        f"strip_reduction_{view}",
        lambda s, d: measures.strip_reduction(tx := make(s, d), least(tx, at)).withColumn("pct", F.round("pct", 6)),
        f"""WITH {q.head(view, at)}, k AS (SELECT count(*) AS occ_after, count(DISTINCT tid) AS tx_after FROM v WHERE item IN (SELECT item FROM s))
SELECT count(*) AS occ_before, any_value(occ_after) AS occ_after, count(DISTINCT tid) - any_value(tx_after) AS tx_emptied,
       round(100.0 * (count(*) - any_value(occ_after)) / count(*), 6) AS pct FROM v, k""",
    )


for _view, _at in AT.items():
    _view_queries(_view, _at)


def _stage_queries(view: str, at: str) -> None:
    make = b.VIEWS[view]
    add(f"item_rank_{view}", lambda s, d: items.rank(items.counts((tx := make(s, d)).rows, least(tx, at))), f"WITH {q.head(view, at)} SELECT item, support, rank FROM s")
    add(
        f"pair_matrix_sparse_{view}",
        lambda s, d: pairs.count_sparse((x := prepared(s, d, view, at)[1]).encoded, x.min_count),
        f"{q.pairs(view, at)} SELECT i, j, support FROM p",
    )
    add(
        f"pair_matrix_dense_{view}",
        lambda s, d: pairs.count_dense((x := prepared(s, d, view, at)[1]).encoded, x.n_items, x.min_count),
        f"{q.pairs(view, at)} SELECT i, j, support FROM p",
    )
    add(
        f"class_members_{view}",
        lambda s, d: classes.members(pairs.count_sparse((x := prepared(s, d, view, at)[1]).encoded, x.min_count)).select("prefix", F.array_join("members", ",").alias("members")),
        f"{q.pairs(view, at)} SELECT i AS prefix, string_agg(CAST(j AS VARCHAR), ',' ORDER BY j) AS members FROM p GROUP BY i",
    )
    for kind in ("per_class", "modulo", "reflect", "snake"):
        add(
            f"class_load_{kind}_{view}",
            lambda s, d, kind=kind: measures.partition_load(pairs.count_sparse((x := prepared(s, d, view, at)[1]).encoded, x.min_count), kind, P),
            f"""{q.pairs(view, at)}, m AS (SELECT i, count(*) AS m FROM p GROUP BY i)
SELECT CAST({q.place(kind, P)} AS INT) AS pid, count(*) AS n_classes, CAST(sum(m) AS BIGINT) AS members, CAST(sum(m * (m - 1) // 2) AS BIGINT) AS pair_candidates FROM m GROUP BY 1""",
        )
    add(
        f"matrix_cells_{view}",
        lambda s, d: measures.matrix_cells(tx := make(s, d), least(tx, at)),
        f"WITH {q.head(view, at)} SELECT count(*) * (count(*) - 1) // 2 AS cells_by_rank, (max(TRY_CAST(item AS BIGINT)) + 1) * max(TRY_CAST(item AS BIGINT)) // 2 AS cells_by_value FROM s",
    )


for _view in ("order_brands", "customer_brands", "turn_words", "order_suppliers"):
    _stage_queries(_view, AT[_view])


def _vertical(layout):
    def run(s, d):
        _, prep = prepared(s, d, "order_brands", "0.02")
        return layout(prep.encoded).select("rank", F.size("tids").cast("bigint").alias("n"), F.aggregate("tids", F.lit(0).cast("bigint"), lambda a, x: a + x).alias("total"), F.array_min("tids").alias("first"), F.array_max("tids").alias("last"))

    return run


_vertical_sql = f"WITH {q.head('order_brands', '0.02')} SELECT rank, support AS n, CAST(list_sum(tids) AS BIGINT) AS total, list_min(tids) AS first, list_max(tids) AS last FROM s"
add("vertical_group_order_brands", _vertical(vertical.by_group), _vertical_sql)
add("vertical_map_order_brands", _vertical(vertical.by_map), _vertical_sql)
add(
    "vertical_round_trip_order_brands",
    lambda s, d: vertical.to_horizontal(vertical.by_group(prepared(s, d, "order_brands", "0.02")[1].encoded)).select("tid", F.array_join("ranks", ",").alias("ranks")),
    f"WITH {q.head('order_brands', '0.02')} SELECT tid, string_agg(CAST(rank AS VARCHAR), ',' ORDER BY rank) AS ranks FROM v JOIN s USING (item) GROUP BY tid",
)
for _view in ("order_brands", "customer_parts", "user_day_keys"):
    add(
        f"strip_tx_{_view}",
        lambda s, d, v=_view: prepared(s, d, v, AT[v])[1].encoded.select("tid", F.array_join("ranks", ",").alias("ranks")),
        f"WITH {q.head(_view, AT[_view])} SELECT tid, string_agg(CAST(rank AS VARCHAR), ',' ORDER BY rank) AS ranks FROM v JOIN s USING (item) GROUP BY tid",
    )
for _at in ("0.01", "0.017", "0.0185", "0.02"):
    add(
        f"strip_curve_customer_parts_{_at.replace('.', '_')}",
        lambda s, d, at=_at: measures.strip_reduction(tx := b.customer_parts(s, d), least(tx, at)).withColumn("pct", F.round("pct", 6)),
        SQL["strip_reduction_customer_parts"].replace("'0.018'", f"'{_at}'"),
    )


def _load_greedy(s, d):
    _, prep = prepared(s, d, "turn_words", "0.2")
    found = pairs.count_sparse(prep.encoded, prep.min_count)
    return measures.partition_load(found, "greedy", P, plan.weights(found))


add("class_load_greedy_turn_words", _load_greedy)


def mined(view: str, at: str, pipeline: str = "filtered_mod", **options):
    return lambda s, d: as_text(plan.mine(b.VIEWS[view](s, d), pipeline, at, **options))


for _view in ("order_brands", "customer_brands", "line_attrs", "line_bins", "user_day_types", "turn_words", "doc_words"):
    for _name in plan.PIPELINES:
        # The word universe is too large for a pair matrix over all items, so it is off there.
        _options = {"matrix": "auto"} if _view == "doc_words" else {}
        add(f"fi_{_name}_{_view}", mined(_view, AT[_view], _name, **_options), q.frequent(_view, AT[_view]))
for _view in ("order_brands", "user_day_types", "turn_words", "customer_brands"):
    _sql = q.frequent(_view, AT[_view])
    add(f"fi_levelwise_{_view}", mined(_view, AT[_view], "levelwise"), _sql)
    add(f"fi_matrix_off_{_view}", mined(_view, AT[_view], matrix=False), _sql)
    add(f"fi_prefix2_{_view}", mined(_view, AT[_view], layout="project", prefix_len=2), _sql)
    add(f"fi_project_greedy_{_view}", mined(_view, AT[_view], layout="project", partitioner="greedy"), _sql)
    add(f"fi_sharded_{_view}", mined(_view, AT[_view], shards=4), _sql)
    add(f"fi_auto_{_view}", mined(_view, AT[_view], "auto"), _sql)
    add(f"fi_fpgrowth_{_view}", lambda s, d, v=_view: as_text(plan.mine_fpgrowth(b.VIEWS[v](s, d), AT[v])), _sql)
for _order in ("support_desc", "lexical"):
    add(f"fi_order_{_order}_order_brands", mined("order_brands", "0.02", order=_order), q.frequent("order_brands", "0.02"))
for _kind in ("snake", "hash", "per_class"):
    add(f"fi_place_{_kind}_order_brands", mined("order_brands", "0.02", partitioner=_kind), q.frequent("order_brands", "0.02"))
add("fi_deep_order_brands", mined("order_brands", "0.005"), q.frequent("order_brands", "0.005"))
add("fi_deep_customer_brands", mined("customer_brands", "0.5"), q.frequent("customer_brands", "0.5"))
add("fi_max_len_turn_words", mined("turn_words", "0.2", max_len=3), f"{q.frequent('turn_words', '0.2')} WHERE k <= 3")
add("fi_bruteforce_user_day_types", lambda s, d: as_text(reference.bruteforce((tx := b.user_day_types(s, d)).rows, least(tx, "0.05"))), q.frequent("user_day_types", "0.05"))
add("fi_sequential_user_day_types", lambda s, d: _sequential(s, d), q.frequent("user_day_types", "0.05"))


def _sequential(s, d):
    tx = b.user_day_types(s, d)
    found = reference.mine_sequential(tx.arrays(), least(tx, "0.05"))
    return s.createDataFrame([("|".join(x), len(x), n) for x, n in found.items()], "itemset string, k int, support bigint")


for _times in (2, 4, 8, 16):
    add(
        f"fi_scaled_x{_times}_order_brands",
        lambda s, d, r=_times: as_text(plan.mine(b.replicated(b.order_brands(s, d), r, 10**12), "filtered_mod", "0.02")),
        q.frequent("order_brands", "0.02", source=f"SELECT tid + r * 1000000000000 AS tid, item FROM ({b.VIEW_SQL['order_brands']}), range({_times}) t(r)"),
    )


def _differing(s, d):
    """Rows by which any pipeline differs from the first: none."""
    tx = b.order_brands(s, d)
    found = [as_text(plan.mine(tx, name, "0.02")) for name in plan.PIPELINES]
    out = None
    for x in found[1:]:
        odd = x.exceptAll(found[0]).unionAll(found[0].exceptAll(x))
        out = odd if out is None else out.unionAll(odd)
    return out.agg(F.count(F.lit(1)).alias("differing"))


add("variant_agreement", _differing, "SELECT CAST(0 AS BIGINT) AS differing")


def _sets(view: str, at: str):
    return lambda s, d: plan.mine(b.VIEWS[view](s, d), "filtered_mod", at)


def _level_candidates(k: int):
    def run(s, d):
        _, prep = prepared(s, d, "turn_words", "0.2")
        level = prep.frequent.select(F.array("rank").alias("ranks"), "support")
        if k == 3:
            level = pairs.count_sparse(prep.encoded, prep.min_count).select(F.array("i", "j").alias("ranks"), "support")
        return levelwise.prune(levelwise.candidates(level), level, k).select(F.array_join("ranks", ",").alias("candidate"))

    return run


add("levelwise_candidates_k2", _level_candidates(2), f"WITH {q.head('turn_words', '0.2')} SELECT a.rank || ',' || b.rank AS candidate FROM s a JOIN s b ON a.rank < b.rank")
add(
    "levelwise_candidates_k3",
    _level_candidates(3),
    f"{q.pairs('turn_words', '0.2')} SELECT a.i || ',' || a.j || ',' || b.j AS candidate FROM p a JOIN p b ON a.i = b.i AND a.j < b.j JOIN p c ON c.i = a.j AND c.j = b.j",
)
for _view, _conf, _inclusive in (("order_brands", 0.15, False), ("turn_words", 0.8, False), ("turn_words", 0.5, True)):
    _sign = ">=" if _inclusive else ">"
    _at = "0.005" if _view == "order_brands" else AT[_view]
    add(
        f"rules_{_view}_{'inclusive' if _inclusive else 'strict'}",
        lambda s, d, v=_view, a=_at, c=_conf, i=_inclusive: rules.generate(_sets(v, a)(s, d), c, b.VIEWS[v](s, d).count(), i).withColumns({"confidence": F.round("confidence", 9), "lift": F.round("lift", 9)}),
        f"""{q.itemsets(_view, _at)},
m AS (SELECT items, k, support, unnest(range(1, (1 << k) - 1)) AS mask FROM f WHERE k > 1),
h AS (SELECT list_filter(items, lambda x, i: (mask & (1 << (i - 1))) <> 0) AS a, list_filter(items, lambda x, i: (mask & (1 << (i - 1))) = 0) AS r, support FROM m)
SELECT array_to_string(a, '|') AS antecedent, array_to_string(r, '|') AS consequent, h.support, round(CAST(h.support AS DOUBLE) / x.support, 9) AS confidence,
       round(CAST(h.support AS DOUBLE) / x.support * (SELECT n FROM n) / y.support, 9) AS lift
FROM h JOIN f x ON x.items = h.a JOIN f y ON y.items = h.r WHERE CAST(h.support AS DOUBLE) / x.support {_sign} {_conf}""",
    )
for _view in ("order_brands", "turn_words"):
    _at = AT[_view]
    add(f"fi_by_length_{_view}", lambda s, d, v=_view: measures.by_length(_sets(v, AT[v])(s, d)).select(F.col("k").cast("int").alias("k"), "n"), f"{q.itemsets(_view, _at)} SELECT k, count(*) AS n FROM f GROUP BY k")
    add(
        f"topk_itemsets_{_view}",
        lambda s, d, v=_view: rules.top_per_length(_sets(v, AT[v])(s, d), 5).select(F.array_join("items", "|").alias("itemset"), F.col("k").cast("int").alias("k"), "support", F.col("place").cast("int").alias("place")),
        f"{q.itemsets(_view, _at)}, r AS (SELECT {q.TEXT} AS itemset, k, support, CAST(row_number() OVER (PARTITION BY k ORDER BY support DESC, {q.TEXT}) AS INT) AS place FROM f) SELECT * FROM r WHERE place <= 5",
    )
    add(f"maximal_{_view}", lambda s, d, v=_view: as_text(rules.maximal(_sets(v, AT[v])(s, d))), f"{q.itemsets(_view, _at)} SELECT {q.TEXT} AS itemset, k, support FROM f WHERE NOT EXISTS (SELECT 1 FROM f g WHERE g.k = f.k + 1 AND list_has_all(g.items, f.items))")
    add(
        f"closed_{_view}",
        lambda s, d, v=_view: as_text(rules.closed(_sets(v, AT[v])(s, d))),
        f"{q.itemsets(_view, _at)} SELECT {q.TEXT} AS itemset, k, support FROM f WHERE NOT EXISTS (SELECT 1 FROM f g WHERE g.k = f.k + 1 AND g.support = f.support AND list_has_all(g.items, f.items))",
    )
add(
    "support_of_order_brands",
    lambda s, d: measures.support_of(b.order_brands(s, d).rows, _sets("order_brands", "0.02")(s, d).where("k = 2").select("items")).select(F.array_join("items", "|").alias("itemset"), "support"),
    f"{q.itemsets('order_brands', '0.02')} SELECT {q.TEXT} AS itemset, support FROM f WHERE k = 2",
)

for _view in ("order_brands", "turn_words", "customer_brands"):
    _at = AT[_view]
    add(
        f"item_vertical_{_view}",
        lambda s, d, v=_view: items.vertical_counts((tx := b.VIEWS[v](s, d)).rows, least(tx, AT[v])).select("item", "support", F.array_min("tids").alias("first"), F.array_max("tids").alias("last"), F.aggregate("tids", F.lit(0).cast("bigint"), lambda a, x: a + x).alias("total")),
        f"WITH {q.head(_view, _at)} SELECT item, support, list_min(tids) AS first, list_max(tids) AS last, CAST(list_sum(tids) AS BIGINT) AS total FROM s",
    )
    add(
        f"intersections_{_view}",
        lambda s, d, v=_view: measures.intersections(tx := b.VIEWS[v](s, d), least(tx, AT[v])),
        f"{q.pairs(_view, _at)}, m AS (SELECT count(*) AS n FROM s), k AS (SELECT count(*) AS p FROM p) SELECT n * (n - 1) // 2 AS all_pairs, p AS with_matrix, n * (n - 1) // 2 - p AS avoided FROM m, k",
    )
    add(
        f"candidates_per_level_{_view}",
        lambda s, d, v=_view: measures.candidates(_sets(v, AT[v])(s, d)).select(F.col("k").cast("int").alias("k"), "classes", "candidates"),
        f"{q.itemsets(_view, _at)}, h AS (SELECT k, items[1:k-1] AS head, count(*) AS m FROM f GROUP BY 1, 2) SELECT k, count(*) AS classes, CAST(sum(m * (m - 1) // 2) AS BIGINT) AS candidates FROM h GROUP BY k",
    )


def _built(matrix: bool):
    """Classes from tid lists: prefix, member and support, with the pair matrix or without."""

    def run(s, d):
        _, prep = prepared(s, d, "order_brands", "0.02")
        found = pairs.count_sparse(prep.encoded, prep.min_count) if matrix else None
        made = classes.build(vertical.by_map(prep.encoded).persist(), prep.min_count, prep.n_items, found)
        return made.select(F.col("prefix")[0].alias("i"), F.col("member").alias("j"), F.size("tids").cast("bigint").alias("support"))

    return run


def _projected(s, d):
    _, prep = prepared(s, d, "order_brands", "0.02")
    found = pairs.count_sparse(prep.encoded, prep.min_count)
    rows = classes.project(prep.encoded, found, found.count()).select(F.col("prefix")[0].alias("i"), F.explode("suffix").alias("j"))
    return rows.groupBy("i", "j").agg(F.count(F.lit(1)).alias("support"))


add("class_build_matrix", _built(True), f"{q.pairs('order_brands', '0.02')} SELECT i, j, support FROM p")
add("class_build_no_matrix", _built(False), f"{q.pairs('order_brands', '0.02')} SELECT i, j, support FROM p")
add("class_project", _projected, f"{q.pairs('order_brands', '0.02')} SELECT i, j, support FROM p")


def _workload(view: str):
    """Itemsets found by the first and the last variant and by level-wise mining at each of the view's falling supports."""
    from vertimine.plans import experiments

    def run(s, d):
        rows = experiments.variants(s, d, (view,), compared)
        return s.createDataFrame([(r["pipeline"], r["min_support"], r["itemsets"]) for r in rows], "pipeline string, min_support string, itemsets bigint")

    compared = ("plain", "filtered_reflect", "levelwise")
    names = ", ".join(f"('{n}')" for n in compared)
    parts = [f"SELECT '{at}' AS min_support, (SELECT count(*) FROM ({q.frequent(view, at)})) AS itemsets" for at in experiments.SUPPORTS[view]]
    add(f"workload_{view}", run, f"SELECT pipeline, min_support, itemsets FROM (VALUES {names}) t(pipeline), ({' UNION ALL '.join(parts)})")


for _view in ("order_brands", "customer_brands", "line_attrs", "user_day_types", "turn_words"):
    _workload(_view)

for _view in ("doc_words", "line_bins", "line_attrs", "user_day_types", "customer_suppliers"):
    for _kind in ("modulo", "reflect"):
        add(
            f"balance_{_kind}_{_view}",
            lambda s, d, kind=_kind, v=_view: measures.partition_load(pairs.count_sparse((x := prepared(s, d, v, AT[v])[1]).encoded, x.min_count), kind, P),
            f"""{q.pairs(_view, AT[_view])}, m AS (SELECT i, count(*) AS m FROM p GROUP BY i)
SELECT CAST({q.place(_kind, P)} AS INT) AS pid, count(*) AS n_classes, CAST(sum(m) AS BIGINT) AS members, CAST(sum(m * (m - 1) // 2) AS BIGINT) AS pair_candidates FROM m GROUP BY 1""",
        )
for _p in (1, 2, 4, 16):
    add(f"fi_p{_p}_customer_brands", mined("customer_brands", AT["customer_brands"], "filtered_mod", p=_p), q.frequent("customer_brands", AT["customer_brands"]))


def _apart(view: b.Transactions) -> b.Transactions:
    """The same transactions with item numbers spread far apart (number * 10000 + 7): a matrix by number is too large, one by rank isn't."""
    far = (F.col("item").cast("bigint") * 10000 + 7).cast("string").alias("item")
    return b.Transactions(view.rows.select("tid", far), view.transactions)


for _name, _options in (("on", {"matrix": True}), ("off", {"matrix": False}), ("auto", {"matrix": "auto", "matrix_by": "value"})):
    add(
        f"fi_matrix_{_name}_spread_order_parts",
        lambda s, d, o=_options: as_text(plan.mine(_apart(b.order_parts(s, d)), "filtered_mod", AT["order_parts"], **o)),
        q.frequent("order_parts", AT["order_parts"], source=f"SELECT tid, CAST(CAST(item AS BIGINT) * 10000 + 7 AS VARCHAR) AS item FROM ({b.VIEW_SQL['order_parts']})"),
    )
add("fi_long_classes_turn_words", mined("turn_words", "0.2", "auto", class_bytes=64), q.frequent("turn_words", "0.2"))
for _at in ("0.2", "0.3"):
    add(
        f"strip_curve_doc_words_{_at.replace('.', '_')}",
        lambda s, d, at=_at: measures.strip_reduction(tx := b.doc_words(s, d), least(tx, at)).withColumn("pct", F.round("pct", 6)),
        SQL["strip_reduction_doc_words"].replace("'0.4'", f"'{_at}'"),
    )


def _itemset_lines(s, d):
    from vertimine.streaming import windows as st

    path = st.shared(s, "itemsets")
    b.write_itemsets(plan.mine(b.order_brands(s, d), min_support="0.02"), path)
    return as_text(b.read_itemsets(s, path))


add("op_itemset_lines", _itemset_lines, q.frequent("order_brands", "0.02", source="SELECT DISTINCT tid, item FROM (" + b.VIEW_SQL["order_brands"] + ")"))

from vertimine import catalogue_ops  # noqa: E402, F401  registers the operator queries
