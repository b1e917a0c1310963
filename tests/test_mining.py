import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from fimspark.operators import encode, localmine, paircounts, pilot, prefixtree, project, rules, stats
from fimspark.plans import accuracy, baselines, budget, cost, grouping, miner
from fimspark.plans.ledger import CostLedger
from fimspark.sources import baskets as B

SF = "/root/testdata/sf0.001"


def rows_of(r):
    got = [(x.itemset, x.support_count) for x in r.fi.collect()]
    assert len(got) == len(set(x for x, _ in got)), "a set was answered twice"
    return dict(got)


def random_lists(seed, rows=120, items="abcdefghij", most=7):
    rng = random.Random(seed)
    return [sorted(rng.sample(items, rng.randint(0, most))) for _ in range(rows)]


def tx_of(spark, lists):
    return spark.createDataFrame(list(enumerate(lists)), "tid long, items array<string>")


def brute(lists, min_count, max_len=None):
    return {"|".join(s): c for s, c in baselines.brute_force(lists, min_count, max_len).items()}


# --- worked examples ---


def test_projection_example(spark):
    """Rows abd, bcd, ac, ab at half of the rows, groups ab and cd."""
    txw = spark.createDataFrame([([1, 2, 4], 1), ([2, 3, 4], 1), ([1, 3], 1), ([1, 2], 1)], "items array<int>, weight long")
    groups = [grouping.Group(1, 2, 0.0), grouping.Group(3, 4, 0.0)]
    proj = project.by_group(txw, groups, 4)
    bag = sorted((r.group_id, tuple(r["items"]), r.weight) for r in proj.collect())
    assert bag == [(0, (1,), 1), (0, (1, 2), 2), (0, (2,), 1), (1, (1, 2, 4), 1), (1, (1, 3), 1), (1, (2, 3, 4), 1)]
    level = miner.mine_level(proj, {0: [1, 2], 1: [3, 4]}, 2)
    got = {(r.group_id, tuple(sorted(r.itemset)), r.support_count) for r in level.where("status = 'fi'").collect()}
    assert got == {(0, (1,), 3), (0, (2,), 3), (0, (1, 2), 2), (1, (3,), 2), (1, (4,), 2), (1, (2, 4), 2)}


def test_order_example(spark):
    tx = tx_of(spark, [list("abc"), list("abcd"), list("ac")])
    mc = encode.resolve_min_count(tx, 0.6)
    assert mc == 2
    assert [r["item"] for r in encode.frequency_order(encode.count_items(tx), mc).orderBy("item_rank").collect()] == ["a", "c", "b"]


def test_thresholds():
    assert encode.resolve_min_count(10, 0.1) == 1 and encode.resolve_min_count(1000, 0.3) == 300 and encode.resolve_min_count(10, 0.25) == 3
    assert encode.resolve_min_count(10, 0.2, strict=True) == 3 and encode.resolve_min_count(10, 4) == 4 and encode.resolve_min_count(10, 4, strict=True) == 5


def test_pass_examples():
    assert cost.passes(2**30, 10 * 2**30, 0.1) == 2 and cost.passes(2**30, 10 * 2**40, 0.1) == 6 and cost.passes(1e9, 1e13, 0.1) == 5 and cost.passes(10, 5, 0.1) == 1


def test_cost_formulas():
    d, b = 4096e3, 4096.0
    assert cost.io_projection(d, 2 * d, b) == 8000 and cost.io_per_item(d, 10, b) == 17000 and cost.io_per_item(d, 10, b, exact=True) == 18500
    assert cost.io_grouped(d, 7, b) == 12500 and cost.io_budgeted(d, 7, b) == 8500 and cost.io_budgeted(d, 7, b, "itemised") == 9500
    assert cost.saving(7, d, b) == 4000 and cost.saving(7, d, b) >= 3.5 * 1000 and cost.extrapolate(10, d, 4 * d, 7) == 40


# --- local mining ---


@pytest.mark.parametrize("seed", range(40))
def test_growth_equals_brute_force(seed):
    lists = [[ord(c) - 96 for c in x] for x in random_lists(seed, 14, "abcdefgh")]
    want = baselines.brute_force(lists, 4)
    frequent = {s[0] for s in want if len(s) == 1}
    ranked = [[i for i in x if i in frequent] for x in lists]
    for options in ({}, {"use_array": False}, {"shared_tree": False}):
        got = localmine.mine_all(localmine.Rows.of(ranked), 4, **options)
        assert len(got) == len({tuple(sorted(s)) for s, _ in got}) and {tuple(sorted(s)): c for s, c in got} == want
    assert dict(baselines.levelwise_local(ranked, 4)) == want
    short = localmine.mine_all(localmine.Rows.of(ranked), 4, max_len=2)
    assert {tuple(sorted(s)): c for s, c in short} == {s: c for s, c in want.items() if len(s) <= 2}


def test_subsets_are_frequent_with_no_less_support():
    fi = baselines.brute_force(random_lists(9), 6)
    for s, c in fi.items():
        for k in range(len(s)):
            if len(s) > 1:
                assert fi[s[:k] + s[k + 1 :]] >= c


def test_array_saves_traversals():
    lists = [[ord(c) - 96 for c in x] for x in random_lists(1)]
    a, b = localmine.Counters(), localmine.Counters()
    localmine.mine_all(localmine.Rows.of(lists), 5, stats=a)
    localmine.mine_all(localmine.Rows.of(lists), 5, use_array=False, stats=b)
    assert a.traversals < b.traversals and a.trees == b.trees


def test_nodes_are_distinct_prefixes(spark):
    lists = [[ord(c) - 96 for c in x] for x in random_lists(2)]
    want = len({tuple(x[: k + 1]) for x in lists for k in range(len(x))})
    assert localmine.node_count(localmine.Rows.of(lists)) == want
    df = spark.createDataFrame(list(enumerate(lists)), "tid long, items array<int>")
    assert prefixtree.count_nodes(df).first()[0] == want and prefixtree.count_nodes(df, exact=True).first()[0] == want
    x = np.zeros((len(lists), 10), np.uint8)
    for r, items in enumerate(lists):
        x[r, [i - 1 for i in items]] = 1
    assert localmine.Tree(x, np.ones(len(lists), np.int64), np.arange(1, 11), True).nodes() == want


# --- groups ---


def bundle(nu, mu, n_used, n_total, nodes):
    return grouping.StatsBundle(len(nu) - 1, n_total, n_used, nodes, np.asarray(nu), np.asarray(mu), n_total / n_used)


def test_cuts_and_packing():
    s = bundle([0, 1, 3, 6, 10, 15, 21], [0, 0, 1, 2, 3, 4, 5], 50, 100, 21)
    assert grouping.cut_ratio(s, 21) == 3 and grouping.cut_nu(s, 21) == 4 and grouping.cut_nu_mu(s, 21) == 3
    groups = grouping.plan(s, 21)
    assert [(g.lo, g.hi) for g in groups] == [(1, 3), (4, 5), (6, 6)]
    assert sorted(a for g in groups for a in g.anchors) == [1, 2, 3, 4, 5, 6]
    none = grouping.plan(bundle([0, 30, 60], [0, 0, 30], 10, 100, 20), 20)
    assert [(g.lo, g.hi, grouping.next_action(g, 20)) for g in none] == [(1, 1, "mine"), (2, 2, "recurse")]
    assert [(g.lo, g.hi) for g in grouping.equal_groups(10, 4)] == [(1, 3), (4, 6), (7, 8), (9, 10)]
    assert grouping.equal_groups(0, 3) == [] and len(grouping.equal_groups(2, 5)) == 2


def test_union_packing_is_not_finer_than_sums():
    lists = [[ord(c) - 96 for c in x] for x in random_lists(4, most=6) if x]
    size = grouping.union_size(lists)
    assert size(1, 10) == len({tuple(x[: k + 1]) for x in lists for k in range(len(x))})
    assert size(3, 5) <= size(3, 3) + size(4, 4) + size(5, 5)


def test_short_circuit_answers_once():
    """Two anchors that are each other's only partner: the pair comes once."""
    direct, left = project.short_circuit([grouping.Group(1, 3, 0.0)], {2: {1: 4}}, {1: 4, 2: 4, 3: 4})
    assert sorted(direct) == [((1,), 4), ((2,), 4), ((2, 1), 4), ((3,), 4)] and left == []
    direct, left = project.short_circuit([grouping.Group(2, 4, 0.0)], {3: {1: 5, 2: 5}, 4: {3: 5}}, {2: 6, 3: 6, 4: 5})
    assert sorted(direct) == [((2,), 6), ((3, 2), 5), ((4,), 5), ((4, 3), 5)] and left[0].anchors == [3]


def test_budget_rules():
    assert budget.usable_nodes(1000) == 900 and budget.usable_nodes(1) == 1 and budget.nodes_for_bytes(2400) == 100
    g = budget.Guard(100)
    g.take(90)
    with pytest.raises(budget.BudgetExceeded):
        g.take(1)


# --- distributed ---


def test_pairs_equal_brute_force(spark, monkeypatch):
    lists = [[ord(c) - 96 for c in x] for x in random_lists(5)]
    df = spark.createDataFrame(list(enumerate(lists)), "tid long, items array<int>")
    want = {}
    for x in lists:
        for i, a in enumerate(x):
            for b in x[i + 1 :]:
                want[b, a] = want.get((b, a), 0) + 1
    for limit in (2000, 3):
        monkeypatch.setattr(paircounts, "DENSE_ITEMS", limit)
        assert {(r.hi, r.lo): r.pair_count for r in paircounts.pair_matrix(df, 10).collect()} == want


@pytest.mark.parametrize("order", ["tid", "hash"])
def test_pilot_stops_at_the_budget(spark, monkeypatch, order):
    monkeypatch.setattr(pilot, "FEW", 3)
    monkeypatch.setattr(pilot, "BINS", 4)
    lists = [x for x in ([ord(c) - 96 for c in y] for y in random_lists(6)) if x]
    df = spark.createDataFrame(list(enumerate(lists)), "tid long, items array<int>").cache()
    key = {r.tid: r.k for r in df.select("tid", (F.col("tid") if order == "tid" else F.pmod(F.xxhash64(F.lit(17), "tid"), F.lit(pilot.SPAN))).alias("k")).collect()}
    for capacity in (1, 7, 60, 10_000):
        p = pilot.build_pilot(df, capacity, order)
        seen, n = set(), 0
        for t in sorted(range(len(lists)), key=key.get):
            new = seen | {tuple(lists[t][: k + 1]) for k in range(len(lists[t]))}
            if len(new) > capacity:
                break
            seen, n = new, n + 1
        assert (p.n_used, p.nodes, p.aborted) == (n, len(seen), n < len(lists))


def test_budgeted_miner_is_exact_under_every_option(spark):
    lists = random_lists(5)
    tx, want = tx_of(spark, lists).cache(), brute(lists, 8)
    whole = prefixtree.count_nodes(miner.prepare(tx, 8).ranked).first()[0]
    for node_budget, options in ((10 * whole, {}), (whole // 2, {}), (whole // 2, {"prune": False, "cut": "nu"}), (whole // 3, {"bypass_head": False, "packing": "union"}), (whole // 3, {"reuse_pilot": True, "cut": "ratio", "array": False, "order": "tid"})):
        r = miner.mine_budgeted(tx, 8, node_budget, measure=True, **options)
        assert rows_of(r) == want
        if node_budget < whole:
            assert all(g["real_nodes"] <= budget.usable_nodes(node_budget) or g["lo"] == g["hi"] for g in r.groups if g["how"] in ("group", "head"))
    assert rows_of(miner.mine_budgeted(tx, 8, whole // 2, max_len=2)) == brute(lists, 8, 2)


def test_recursion_and_splits_are_exact(spark):
    lists = random_lists(8, 60, "abcdefg", 6)
    tx = tx_of(spark, lists).cache()
    r = miner.mine_budgeted(tx, 6, 18)
    assert rows_of(r) == brute(lists, 6) and {g["how"] for g in r.groups} & {"split", "whole"}


@pytest.mark.parametrize("k", [1, 2, 3, 6])
def test_any_grouping_gives_the_same(spark, k):
    lists = random_lists(7)
    assert rows_of(miner.mine_equal_groups(tx_of(spark, lists), 8, k)) == brute(lists, 8)


def test_baselines_agree(spark):
    lists = random_lists(11)
    tx, want = tx_of(spark, lists).cache(), brute(lists, 12)
    assert rows_of(miner.mine_per_item(tx, 12)) == want
    assert rows_of(baselines.in_memory(tx, 12, use_array=False)) == want
    assert rows_of(baselines.levelwise(tx, 12)) == want
    assert rows_of(baselines.partitioned(tx, 0.1, 3)) == want
    assert rows_of(baselines.partitioned(tx, 0.1, 3, candidate_store="shuffle")) == want
    assert rows_of(baselines.persisted_tree(tx, 12)) == want
    assert rows_of(baselines.vertical(tx, 12)) == want and rows_of(baselines.vertical(tx, 12, diffsets=False)) == want
    assert rows_of(baselines.sampled(tx, 0.1, 1.0)) == want
    some = rows_of(baselines.sampled(tx, 0.1, 0.3))
    assert set(some.items()) <= set(want.items())


def test_nothing_frequent_and_odd_baskets(spark):
    tx = tx_of(spark, [[], ["a"], ["b"], ["a", "b"]])
    for r in (miner.mine_budgeted(tx, 10, 100), miner.mine_per_item(tx, 10), miner.mine_equal_groups(tx, 10, 2), baselines.levelwise(tx, 10), baselines.vertical(tx, 10), baselines.persisted_tree(tx, 10), baselines.in_memory(tx, 10)):
        assert r.fi.count() == 0 and r.fi.columns == ["itemset", "size", "support_count"]
    assert rows_of(miner.mine_budgeted(tx, 1, 100)) == {"a": 2, "b": 2, "a|b": 1}
    none = tx.limit(0)
    assert miner.mine_budgeted(none, 1, 100).fi.count() == 0
    assert rows_of(miner.mine_budgeted(tx_of(spark, [["é"], ["z"], ["é"]]), 2, 100)) == {"é": 2}


def test_library_agrees(spark):
    from pyspark.ml.fpm import FPGrowth

    tx = B.order_brands(spark, SF).cache()
    got = rows_of(miner.mine_budgeted(tx, 0.02, 300))
    theirs = {"|".join(sorted(r["items"])): r.freq for r in FPGrowth(itemsCol="items", minSupport=0.02).fit(tx).freqItemsets.collect()}
    assert got == theirs


def test_candidates_and_recall(spark):
    tx = B.order_brands(spark, SF).cache()
    exact = baselines.in_memory(tx, 0.02)
    part = baselines.partitioned(tx, 0.02, 4)
    f = accuracy.false_hits(part.candidates, part.fi).first()
    assert f.candidates - f.false_hits == exact.fi.count()
    r = accuracy.recall(baselines.sampled(tx, 0.02, 0.5).fi, exact.fi).first()
    assert 0 < r.recall <= 1 and r.missed == round(r.n * (1 - r.recall))


def test_estimates_and_ledger(spark):
    tx = B.order_brands(spark, "/root/testdata/sf0.01").cache()
    r = miner.mine_budgeted(tx, 0.005, 7453, measure=True, prune=False)
    e = accuracy.group_estimates(spark, r, 6707).collect()
    assert len(e) == 6 and [g.hi for g in e][0] in (14, 15, 16) and all(0.5 < g.ratio < 2 for g in e)
    per_item = miner.mine_per_item(tx, 0.005, measure=True)
    assert 0 < r.ledger.expansion() < per_item.ledger.expansion(), "grouping writes less than per-item projection"
    assert {x.phase for x in r.ledger.to_frame(spark).collect()} >= {"ranked", "projected"}
    assert CostLedger().expansion() == 0.0


def test_rules_closed_and_maximal(spark):
    lists = random_lists(12)
    tx = tx_of(spark, lists)
    fi = baselines.in_memory(tx, 10).fi.cache()
    want = baselines.brute_force(lists, 10)
    closed = {"|".join(s) for s, c in want.items() if not any(set(s) < set(t) and d == c for t, d in want.items())}
    maximal = {"|".join(s) for s in want if not any(set(s) < set(t) for t in want)}
    assert {r.itemset for r in rules.closed(fi).collect()} == closed and {r.itemset for r in rules.maximal(fi).collect()} == maximal
    got = {(r.antecedent, r.consequent): r for r in rules.generate(fi, len(lists), 0.4).collect()}
    n = len(lists)
    for s, c in want.items():
        for m in range(1, 2 ** len(s) - 1):
            a = tuple(x for k, x in enumerate(s) if m >> k & 1)
            b = tuple(x for k, x in enumerate(s) if not m >> k & 1)
            r = got.get(("|".join(a), "|".join(b)))
            assert (r is not None) == (c >= 0.4 * want[a])
            if r:
                assert r.confidence == round(c / want[a], 6) and r.lift == round(c * n / (want[a] * want[b]), 6)


def test_larger_dictionaries_are_joined(spark, monkeypatch):
    lists = random_lists(13)
    tx, want = tx_of(spark, lists), brute(lists, 10)
    monkeypatch.setattr(encode, "MAX_SENT_ITEMS", 3)
    assert rows_of(miner.mine_budgeted(tx, 10, 60)) == want


def test_experiments_move_as_reported(spark):
    from fimspark.plans import experiments

    tx = B.order_brands(spark, "/root/testdata/sf0.01")
    by = {(r.share, r.method): r for r in experiments.compare(spark, tx, "w1", [0.01, 0.005], 7453).collect()}
    for share in (0.01, 0.005):
        assert by[share, "grouped"].moved_cells < by[share, "per item"].moved_cells
        assert by[share, "grouped"].groups < by[share, "per item"].groups
        assert len({by[share, m].itemsets for m in ("grouped", "per item", "partitioned")}) == 1
    assert by[0.005, "partitioned"].moved_cells >= by[0.01, "partitioned"].moved_cells, "candidates grow as the share falls"
    p = miner.prepare(B.customer_brands(spark, "/root/testdata/sf0.01"), 0.5)
    volume = experiments.volume_by_groups(spark, p.ranked, p.n, [1, 2, 5, 25]).collect()
    assert [v.expansion for v in volume] == sorted(v.expansion for v in volume) and volume[0].expansion == 1
    assert all(abs(v.expansion / v.formula - 1) < 0.35 for v in volume)


# --- budgets, plans and what is written ---


@pytest.mark.parametrize("node_budget", [10, 60])
def test_no_task_passes_its_budget(spark, node_budget):
    lists = random_lists(21, 150, "abcdefgh", 7)
    tx, want = tx_of(spark, lists).cache(), brute(lists, 6)
    assert prefixtree.count_nodes(miner.prepare(tx, 6).ranked).first()[0] > 2 * node_budget
    for r in (
        miner.mine_budgeted(tx, 6, node_budget),
        miner.mine_budgeted(tx, 6, node_budget, array=False, prune=False, shared_tree=False),
        miner.mine_per_item(tx, 6, node_budget),
        miner.mine_equal_groups(tx, 6, 3, node_budget),
    ):
        assert rows_of(r) == want
        assert 0 < r.counters.nodes <= budget.usable_nodes(node_budget) and r.counters.held <= node_budget
    if node_budget == 10:
        assert max(g["depth"] for g in miner.mine_per_item(tx, 6, node_budget).groups) >= 1, "databases over the budget are projected again"


def test_trees_without_room_are_mined_in_place():
    lists = [[ord(c) - 96 for c in x] for x in random_lists(22, 200, "abcdefghi", 8)]
    rows = localmine.Rows.of([x for x in lists if x])
    want = baselines.brute_force(lists, 9)
    frequent = sorted(s[0] for s in want if len(s) == 1)
    n = localmine.node_count(rows)
    for capacity in (n, 10 * n):
        seen = localmine.Counters()
        got = list(localmine.mine_group(rows, frequent, 9, capacity=capacity, stats=seen))
        assert {tuple(sorted(s)): c for s, c in got if set(s) <= set(frequent)} == want and seen.held <= capacity + capacity // 9
    with pytest.raises(budget.BudgetExceeded):
        list(localmine.mine_group(rows, frequent, 9, capacity=n - 1))


def test_header_links_hold_each_items_nodes():
    lists = [[ord(c) - 97 for c in x] for x in random_lists(23) if x]
    t = localmine.Tree.of(localmine.Rows.of(lists), np.arange(10), True)
    assert all((t.item[t.of_item(j)] == j).all() for j in range(10)) and sum(len(t.of_item(j)) for j in range(10)) == t.nodes()
    assert (t.parent < np.arange(t.nodes())).all(), "parents come first"
    for j in range(10):
        assert t.support(j) == sum(j in x for x in lists)
        above = t.partners(t.of_item(j), t.count[t.of_item(j)])
        assert above[:j].tolist() == t.pairs[j, :j].tolist() == [sum(i in x and j in x for x in lists) for i in range(j)]


def test_partners_that_come_with_a_group_save_climbs(spark):
    tx = B.order_brands(spark, "/root/testdata/sf0.01").cache()
    a, b = miner.mine_budgeted(tx, 0.005, 7453), miner.mine_budgeted(tx, 0.005, 7453, array=False)
    assert rows_of(a) == rows_of(b) and a.counters.traversals < b.counters.traversals


def test_quick_pilot_equals_the_relational_one(spark):
    lists = [x for x in ([ord(c) - 96 for c in y] for y in random_lists(24)) if x]
    df = spark.createDataFrame(list(enumerate(lists)), "tid long, items array<int>").cache()
    pairs = paircounts.pair_matrix(df, 10).cache()
    for order in ("tid", "hash"):
        txw = df.select("items", pilot.order_key(order).alias("k")).groupBy("items").agg(F.count(F.lit(1)).alias("weight"), F.min("k").alias("k")).cache()
        for capacity in (7, 60, 10_000):
            p = pilot.build_pilot(df, capacity, order)
            count = lambda stop: df.where(pilot.order_key(order) <= stop).count()
            q = pilot.quick_pilot(txw, 10, capacity, sum(map(len, lists)), len(lists), order == "hash", True, True, count)
            assert (q.nodes, q.aborted) == (p.nodes, p.aborted)
            want = stats.collect_stats(p, pairs, 10, 5)
            assert np.cumsum(q.nu).tolist() == want.nu.tolist() and q.mu(pairs, miner._frequent(pairs, 5), 5).tolist() == want.mu.tolist() == q.mu(pairs, None, 5).tolist()
            assert len(q.tree[0]) == q.nodes
            if q.aborted:
                kept = {tuple(r["items"]) for r in p.rows.collect()}
                assert {tuple(r["items"]) for r in q.rows.collect()} == kept
                if order == "tid":
                    assert q.n_used == p.n_used


def test_plans_by_join_equal_those_on_the_driver(spark, monkeypatch):
    lists = random_lists(25, 200, "abcdefghij", 5)
    tx, want = tx_of(spark, lists).cache(), brute(lists, 14)
    p = miner.prepare(tx, 14)
    pairs = paircounts.pair_matrix(p.ranked, p.n).cache()
    frequent = miner._frequent(pairs, 14)
    for groups in (grouping.equal_groups(p.n, 3), grouping.equal_groups(p.n, p.n)):
        direct, left = project.short_circuit(groups, frequent, p.counts)
        left = project.prune_companions(left, frequent)
        other, joined = project.planned_by_join(pairs, groups, p.n, p.counts, 14)
        assert sorted(direct) == sorted(other) and [(g.lo, g.anchors, g.companions) for g in left] == [(g.lo, g.anchors, g.companions) for g in joined]
    monkeypatch.setattr(miner, "MAX_PLANNED_PAIRS", 0)
    monkeypatch.setattr(miner, "HEAD_CELLS", 0)
    assert rows_of(miner.mine_budgeted(tx, 14, 40)) == want


def test_ledger_has_all_that_is_written(spark):
    tx = B.order_brands(spark, "/root/testdata/sf0.01").cache()
    r = miner.mine_budgeted(tx, 0.005, 7453, measure=True)
    e = {p: (n, c) for p, n, c, _ in r.ledger.entries}
    rows = [tuple(x["items"]) for x in miner.prepare(tx, 0.005).ranked.collect()]
    assert e["ranked"] == (len(rows), sum(map(len, rows))) and e["collapsed"] == (len(set(rows)), sum(map(len, set(rows))))
    assert e["head"] == (0, 0) and e["projected"][1] > 0 and e["pilot rows"][0] > 0 and e["pairs"][0] == 300
    assert r.ledger.written() == sum(c for p, (_, c) in e.items() if p != "ranked")
    staged = miner.mine_budgeted(tx, 0.005, 7453, measure=True, bypass_head=False)
    assert staged.ledger.cells("projected") > r.ledger.cells("projected"), "a head that is projected is counted"


def test_pair_counts_take_bounded_memory():
    import tracemalloc

    rng = np.random.default_rng(0)
    rows = np.sort(np.argsort(rng.random((10_000, 1000)), axis=1)[:, :100] + 1, axis=1).astype(np.int32)
    offsets = np.arange(0, 1_000_001, 100)
    tracemalloc.start()
    total = sum(len(k) for k, _ in paircounts._pairs_of(offsets, rows.ravel(), np.ones(10_000, np.int64), 1000))
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert total == 10_000 * 4950 and peak < 100 << 20
    long = np.arange(1, 2001, dtype=np.int32)
    got = np.concatenate([k for k, _ in paircounts._pairs_of(np.asarray([0, 2000]), long, np.ones(1, np.int64), 2000)])
    assert len(np.unique(got)) == len(got) == 2000 * 1999 // 2


def test_cells_follow_from_memory(spark, monkeypatch):
    tx = B.order_brands(spark, SF).cache()
    want = rows_of(baselines.in_memory(tx, 0.02))
    one = baselines.partitioned(tx, 0.02)
    monkeypatch.setattr(baselines, "CELL_ITEMS", 500)
    some = baselines.partitioned(tx, 0.02)
    assert one.cells == 1 < some.cells and rows_of(one) == rows_of(some) == want


def test_task_metrics(spark):
    from fimspark.plans import metrics

    with metrics.TaskMetrics(spark) as m:
        spark.range(100_000).groupBy((F.col("id") % 100).alias("k")).count().collect()
    assert m.total["shuffle_mb"] > 0 and m.total["compute_s"] > 0 and m.total["spill_mb"] == 0 and m.total["wall_s"] > 0
    assert metrics.to_frame(spark, [("x", m.total)]).count() == 1


def test_rules_of_long_sets(spark, monkeypatch):
    monkeypatch.setattr(rules, "HALF", 2)
    lists = random_lists(12)
    fi = baselines.in_memory(tx_of(spark, lists), 10).fi.cache()
    few = {tuple(r) for r in rules.generate(fi, len(lists), 0.4).collect()}
    monkeypatch.setattr(rules, "HALF", 12)
    assert few == {tuple(r) for r in rules.generate(fi, len(lists), 0.4).collect()} and few


def test_patterns_lose_items(spark):
    from fimspark.sources import synth

    whole, some = synth.baskets(spark, 300, 500, 40, 20, 50), synth.baskets(spark, 300, 500, 40, 20, 50, corruption=0.5)
    assert baselines.in_memory(some, 0.1, max_len=2).fi.count() < baselines.in_memory(whole, 0.1, max_len=2).fi.count()


@pytest.mark.parametrize("shared_tree", [True, False])
def test_partners_that_left_a_group_are_not_answered_again(spark, shared_tree):
    """Line attributes: some anchors of a group have one partner, are answered directly and leave it."""
    tx = B.WORKLOADS["w7"](spark, SF).cache()
    n = tx.count()
    r = miner.mine_budgeted(tx, 0.02, 1500, shared_tree=shared_tree)
    assert rows_of(r) == rows_of(baselines.in_memory(tx, 0.02)) and n > 0 and len(r.groups) > 1


def test_a_head_read_in_many_batches_is_whole(spark):
    """More baskets than nodes, but fewer distinct ones once they are cut: none is left out."""
    rng = random.Random(3)
    lists = [[x for x in range(1, 13) if rng.random() < 0.5] for _ in range(3000)]
    rows = spark.createDataFrame([(0, [i for i in x if i <= 4], 1) for x in lists if min(x, default=9) <= 4], "group_id long, items array<int>, weight long").repartition(5)
    level = miner.mine_level(rows, {0: [1, 2, 3, 4]}, 1, capacity=20, direct=True)
    got = {tuple(sorted(r.itemset)): r.support_count for r in level.where("status = 'fi'").collect()}
    assert got == baselines.brute_force([[i for i in x if i <= 4] for x in lists], 1)
    assert [r.status for r in miner.mine_level(rows, {0: [1, 2, 3, 4]}, 1, capacity=5, direct=True).collect()] == ["needs_split"]


def test_stages_of_a_run_are_removed(spark):
    from pathlib import Path

    from fimspark.session import shared_dir

    folder = Path(shared_dir(spark).removeprefix("file:"))
    files = lambda: {p.name for p in folder.glob("rdd-*")}
    tx = tx_of(spark, random_lists(31)).cache()
    before = files()
    r = miner.mine_budgeted(tx, 8, 40)
    n = r.fi.count()
    made = files() - before
    assert r.scratch == [] and rows_of(r) == brute(random_lists(31), 8) and n > 0
    bare = miner.mine_budgeted(tx, 8, 10_000)
    assert len(made) < 12 and bare.fi.count() == n
    with pytest.raises(ValueError):
        miner.mine_budgeted(tx, 8)


def test_trees_too_large_for_a_task_are_counted(spark):
    """As large as tasks without a limit make them, and given for planned groups that no task could hold."""
    lists = random_lists(21, 200, "abcdefghij", 7)
    tx = tx_of(spark, lists).cache()
    p = miner.prepare(tx, 8)
    pairs, groups = paircounts.pair_matrix(p.ranked, p.n).cache(), [grouping.Group(1, 3, 0.0), grouping.Group(4, 4, 0.0), grouping.Group(5, 5, 0.0), grouping.Group(6, p.n, 0.0)]
    proj, anchors = project.by_group(encode.collapse(p.ranked), groups, p.n), {k: g.anchors for k, g in enumerate(groups)}
    for shared in (True, False):
        level = miner.mine_level(proj, anchors, p.min_count, shared_tree=shared, partners=project.partner_rows(pairs, groups, p.n, p.min_count))
        made = {r["group_id"]: r["support_count"] for r in level.where("status = 'nodes'").collect()}
        assert miner._tree_sizes(proj, anchors, pairs, p.min_count, shared) == made and min(made.values()) > 0
    few, every = (miner.mine_budgeted(tx, 8, 60, prune=False, sizes=x) for x in (False, True))
    assert rows_of(every) == rows_of(few) == brute(lists, 8)
    planned = []
    for g in every.groups:  # the plan for the table itself comes first
        planned.append(g)
        if g["hi"] == p.n:
            break
    assert [a for g in planned for a in range(g["lo"], g["hi"] + 1)] == [*range(1, p.n + 1)]
    assert any(g["real_nodes"] > budget.usable_nodes(60) for g in planned) and len(few.groups) < len(every.groups)


def test_ledger_of_the_plan_and_of_side_by_side_databases():
    import time
    from concurrent.futures import ThreadPoolExecutor

    class Seen:
        @property
        def get(self):
            time.sleep(0.05)
            return {"n": 1, "cells": 2}

    ledger = CostLedger()
    ledger.add("ranked", 5, 9)
    ledger.add("projected", 4, 7)
    ledger.watched = [("projected again", Seen()), ("projected", Seen())]
    with ThreadPoolExecutor(2) as pool:
        [f.result() for f in [pool.submit(ledger.settle) for _ in range(2)]]
    ledger.add("collapsed", 3, 3)
    assert ledger.written() == 7 + 2 + 2 + 3, "nothing is entered twice"
    deeper = CostLedger(entries=[*ledger.entries[:2], ("projected again", 1, 2, 0.0), ("projected", 1, 2, 0.0)])
    assert [e[:3] for e in deeper.planned().entries] == [("ranked", 5, 9), ("projected", 4, 7)] and deeper.written() == 11
