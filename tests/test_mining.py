"""Worked examples, invariants over pipelines, baselines and options."""

from itertools import combinations

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from vertimine import catalogue, measures, threshold
from vertimine.operators import bottomup, chunks, classes, encode, items, levelwise, pairs, partitioners, reference, rules, vertical
from vertimine.plans import mine as plan
from vertimine.sources import baskets as b

MICRO = [(1, ["a", "b", "c"]), (2, ["a", "b", None, "b"]), (3, ["b", "c", "d"]), (4, ["a", "c"]), (5, ["a", "b", "c", "d"]), (6, [])]


def brute(rows, least):
    found = {}
    for _, xs in rows:
        xs = sorted({x for x in xs if x is not None})
        for k in range(1, len(xs) + 1):
            for c in combinations(xs, k):
                found[c] = found.get(c, 0) + 1
    return {c: n for c, n in found.items() if n >= least}


def tx_of(spark, rows):
    return b.Transactions.from_arrays(spark.createDataFrame(rows, "tid bigint, items array<string>"))


def as_dict(df):
    return {tuple(r["items"]): r["support"] for r in df.collect()}


def test_threshold_is_decimal():
    assert threshold.resolve(30, 0.1) == 3
    assert threshold.resolve(31, 0.1) == 4
    assert threshold.resolve(0, 0.5) == 1
    assert threshold.resolve(10, min_count=4) == 4
    for bad in ({"min_support": 0}, {"min_support": 1.5}, {"min_count": 0}, {}, {"min_support": 0.5, "min_count": 1}):
        with pytest.raises(ValueError):
            threshold.resolve(10, **bad)


def test_five_item_classes(spark):
    """All pairs of 1..5 frequent: members 2345, 345, 45, 5; joins give 6, 3 and 1 triples."""
    p = spark.createDataFrame([(i, j, 1) for i, j in combinations(range(1, 6), 2)], "i int, j int, support bigint")
    assert {r["prefix"]: list(r["members"]) for r in classes.members(p).collect()} == {1: [2, 3, 4, 5], 2: [3, 4, 5], 3: [4, 5], 4: [5]}
    level = p.select(F.array("i", "j").alias("ranks"), "support")
    triples = [tuple(r["ranks"]) for r in levelwise.prune(levelwise.candidates(level), level, 3).collect()]
    assert [sum(t[0] == i for t in triples) for i in (1, 2, 3, 4)] == [6, 3, 1, 0]


@pytest.mark.parametrize("pipeline", [*plan.PIPELINES, "auto", "levelwise"])
def test_micro_database(spark, pipeline):
    tx = tx_of(spark, MICRO)
    assert tx.count() == 6
    for least in (1, 2, 3, 4, 5):
        assert as_dict(plan.mine(tx, pipeline, min_count=least)) == brute(MICRO, least), least


@pytest.mark.parametrize("options", [{"matrix": False}, {"matrix": "auto"}, {"layout": "project", "prefix_len": 2}, {"layout": "project", "prefix_len": 3}, {"shards": 3}, {"partitioner": "greedy", "layout": "project"}, {"partitioner": "snake", "p": 3}, {"partitioner": "hash"}, {"order": "lexical"}, {"order": "support_desc"}, {"p": 50}])
def test_options_do_not_change_the_answer(spark, options):
    tx = tx_of(spark, MICRO)
    assert as_dict(plan.mine(tx, "filtered_mod", min_count=2, **options)) == brute(MICRO, 2)


def test_edges(spark):
    empty = tx_of(spark, [(1, [])])
    assert as_dict(plan.mine(empty, min_count=1)) == {}
    one = tx_of(spark, [(1, ["x"]), (2, ["x"])])
    same = tx_of(spark, [(i, ["ä", "y", "z"]) for i in range(5)])
    for name in plan.PIPELINES:
        assert as_dict(plan.mine(one, name, min_count=1)) == {("x",): 2}
        assert as_dict(plan.mine(one, name, min_count=3)) == {}
        assert set(as_dict(plan.mine(same, name, min_support=1.0)).values()) == {5}
        assert len(as_dict(plan.mine(same, name, min_support=1.0))) == 7
    assert as_dict(plan.mine(same, min_count=1, max_len=2)) == {c: n for c, n in brute([(i, ["ä", "y", "z"]) for i in range(5)], 1).items() if len(c) <= 2}
    assert as_dict(plan.mine(same, min_count=1, include_singletons=False)) == {c: n for c, n in brute([(i, ["ä", "y", "z"]) for i in range(5)], 1).items() if len(c) > 1}


def test_partitioner_grid(spark):
    v = spark.range(12).select(F.col("id").cast("int").alias("v"))

    def ids(c):
        return "".join(str(r[0]) for r in v.orderBy("v").select(c).collect())

    assert ids(partitioners.modulo(F.col("v"), 4)) == "012301230123"
    assert ids(partitioners.reflect(F.col("v"), 4)) == "012332103210"
    assert ids(partitioners.snake(F.col("v"), 4)) == "012332100123"
    assert partitioners.greedy({0: 5, 1: 3, 2: 3, 3: 1}, 2) == {0: 0, 1: 1, 2: 1, 3: 0}
    with pytest.raises(ValueError):
        partitioners.column("none", F.col("v"), 4)


def test_one_exchange_places_the_classes(spark):
    made = spark.createDataFrame([([0], 1, [1, 2]), ([1], 1, [2])], "prefix array<int>, tid bigint, suffix array<int>")
    plan_text = bottomup.mine(made, F.col("prefix")[0], 2, 1)._jdf.queryExecution().executedPlan().toString()
    assert plan_text.count("Exchange") == 1 and "REPARTITION_BY_NUM" in plan_text.upper() or plan_text.count("Exchange") == 1


def test_dense_equals_sparse_and_pairs_equal_two_sets(spark, sf):
    tx = b.order_brands(spark, sf)
    prep = plan.prepare(tx, plan.MiningConfig(), "0.02")
    enc = encode.strip(tx.rows, prep.frequent, prep.n_items)
    sparse = sorted(map(tuple, pairs.count_sparse(enc, prep.min_count).collect()))
    assert sparse == sorted(map(tuple, pairs.count_dense(enc, prep.n_items, prep.min_count).collect()))
    assert len(sparse) == plan.mine(tx, "filtered", "0.02").where("k = 2").count()


def test_vertical_ways_agree_and_round_trip(spark, sf):
    tx = b.user_day_types(spark, sf)
    prep = plan.prepare(tx, plan.MiningConfig(), "0.05")
    enc = encode.strip(tx.rows, prep.frequent, prep.n_items)
    group = {r["rank"]: list(r["tids"]) for r in vertical.by_group(enc).collect()}
    assert group == {r["rank"]: list(r["tids"]) for r in vertical.by_map(enc).collect()}
    back = {r["tid"]: list(r["ranks"]) for r in vertical.to_horizontal(vertical.by_map(enc)).collect()}
    assert back == {r["tid"]: list(r["ranks"]) for r in enc.collect()}
    known = {r["item"]: r["rank"] for r in prep.frequent.collect()}
    assert back == {r["tid"]: list(r["ranks"]) for r in encode.strip_arrays(b.to_arrays(tx.rows), known).collect()}


def test_baselines_agree(spark, sf):
    tx = b.user_day_types(spark, sf)
    own = as_dict(plan.mine(tx, "filtered_reflect", "0.05"))
    least = threshold.resolve(tx.count(), "0.05")
    assert own == as_dict(reference.bruteforce(tx.rows, least))
    assert own == as_dict(plan.mine_fpgrowth(tx, "0.05"))
    assert own == reference.mine_local({r["tid"]: r["items"] for r in b.to_arrays(tx.rows).collect()}, least)
    for c, n in own.items():  # every subset is there with at least the support
        for part in combinations(c, len(c) - 1):
            assert not part or own[part] >= n


def test_sequential_mining_sends_no_transactions(spark, sf, monkeypatch):
    """The driver gets bitmaps, not transactions; the itemsets are those of mining the transactions themselves."""
    tx = b.user_day_types(spark, sf)
    least, local, sent = threshold.resolve(tx.count(), "0.05"), {r["tid"]: r["items"] for r in b.to_arrays(tx.rows).collect()}, []
    kind = type(tx.rows)
    for name, size in (("collect", len), ("toArrow", lambda t: t.num_rows)):
        monkeypatch.setattr(kind, name, lambda df, made=getattr(kind, name), size=size: sent.append(size(found := made(df))) or found)
    assert catalogue.QUERIES["fi_sequential_user_day_types"](spark, sf) is not None
    assert sum(sent) < len(local) // 4
    assert reference.mine_sequential(tx.arrays(), least) == reference.mine_local(local, least)
    assert reference.mine_sequential(tx.arrays(), 10**9) == {}


def test_pairs_of_unstripped_lists_are_of_frequent_items_only(spark):
    """Lists of many rare items cost no intersections; the frequent pairs are the same."""
    rows = [([0, 1, 2 + n % 3, *range(10 + 400 * n, 410 + 400 * n)],) for n in range(60)]
    encoded = spark.createDataFrame(rows, "ranks array<int>").repartition(2)
    want = sorted(map(tuple, chunks.pair_supports(spark.createDataFrame([(x[0][:3],) for x in rows], "ranks array<int>"), 5, 15).collect()))
    assert sorted(map(tuple, chunks.pair_supports(encoded, 24_010, 15, 5).collect())) == want and len(want) == 7


def test_counting_by_join_equals_scan(spark, sf):
    tx = b.user_day_types(spark, sf)
    prep = plan.prepare(tx, plan.MiningConfig(), "0.01")
    enc = encode.strip(tx.rows, prep.frequent, prep.n_items)
    wanted = [tuple(c) for c in combinations(range(prep.n_items), 3)]
    scan = {tuple(r["ranks"]): r["support"] for r in levelwise.count_scan(enc, wanted, 3).collect()}
    join = {tuple(r["ranks"]): r["support"] for r in levelwise.count_join(enc, spark.createDataFrame([(list(c),) for c in wanted], "ranks array<int>"), 3).collect()}
    assert scan == join


def test_replication_scales_supports(spark, sf):
    tx = b.order_brands(spark, sf)
    once = as_dict(plan.mine(tx, min_support="0.05"))
    twice = as_dict(plan.mine(b.replicated(tx, 2, 10**12), min_support="0.05"))
    assert twice == {c: 2 * n for c, n in once.items()}


def test_rules(spark):
    sets = plan.mine(tx_of(spark, MICRO), min_count=2)
    strict = {(r["antecedent"], r["consequent"]): r["confidence"] for r in rules.generate(sets, 0.75, 6).collect()}
    loose = {(r["antecedent"], r["consequent"]): r["confidence"] for r in rules.generate(sets, 0.75, 6, inclusive=True).collect()}
    assert ("d", "b|c") in strict and strict["d", "b|c"] == 1.0
    assert ("a", "b") in loose and ("a", "b") not in strict
    support = as_dict(sets)
    for (x, y), c in loose.items():
        assert c == support[tuple(sorted(x.split("|") + y.split("|")))] / support[tuple(x.split("|"))]
    most = as_dict(rules.maximal(sets).select("items", "support"))
    assert all(not any(set(c) < set(o) for o in support) for c in most)
    closed = as_dict(rules.closed(sets).select("items", "support"))
    assert closed == {c: n for c, n in support.items() if not any(set(c) < set(o) and support[o] == n for o in support)}


def test_measures(spark, sf):
    tx = tx_of(spark, MICRO)
    row = measures.profile(tx).first()
    assert (row["transactions"], row["items"], row["occurrences"], row["max_width"]) == (6, 4, 14, 4)
    cut = measures.strip_reduction(tx, 4).first()
    assert (cut["occ_before"], cut["occ_after"], cut["tx_emptied"]) == (14, 12, 0)
    p = spark.createDataFrame([(0, 1, 3), (0, 2, 3), (1, 2, 3)], "i int, j int, support bigint")
    load = measures.partition_load(p, "modulo", 2)
    assert {r["pid"]: (r["n_classes"], r["members"], r["pair_candidates"]) for r in load.collect()} == {0: (1, 2, 1), 1: (1, 1, 0)}
    assert measures.imbalance(load, 2) == pytest.approx(4 / 3)
    assert pairs.mode(100) == "dense" and pairs.mode(100, 20_000_000, by="value") == "sparse"
    told = {tuple(r["items"]): r["support"] for r in measures.support_of(tx.rows, spark.createDataFrame([(["a", "b"],), (["d"],)], "items array<string>")).collect()}
    assert told == {("a", "b"): 3, ("d",): 2}


@settings(max_examples=60, deadline=None)
@given(st.lists(st.sets(st.integers(0, 7)), max_size=14), st.integers(1, 4))
def test_class_miner_against_brute_force(rows, least):
    found = reference.mine_local({n: [str(x) for x in xs] for n, xs in enumerate(rows)}, least)
    assert found == brute([(n, [str(x) for x in xs]) for n, xs in enumerate(rows)], least)


def test_rank_orders(spark):
    counted = items.counts(tx_of(spark, MICRO).rows)
    got = {o: [r["item"] for r in items.rank(counted, o).orderBy("rank").collect()] for o in items.ORDERS}
    assert got["lexical"] == ["a", "b", "c", "d"] and got["support_asc"][0] == "d" and got["support_desc"][-1] == "d"
    with pytest.raises(ValueError):
        items.rank(counted, "random")
