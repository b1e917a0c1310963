import math

import duckdb
import pandas as pd
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from fimspark import queries as catalogue
from fimspark.functions import sqlapi
from fimspark.operators import relops
from fimspark.plans import budget
from fimspark.sources import baskets as B
from fimspark.sources import synth
from fimspark.sources.tables import read_baskets, table, write_baskets
from fimspark.streaming import events as S

SF = "/root/testdata/sf0.01"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
SOME = [
    "mine_budgeted_w1",
    "mine_budgeted_w6",
    "mine_per_item_w1",
    "partitioned_w6",
    "vertical_w1",
    "pair_matrix",
    "mu_anchor",
    "pilot_cutoff",
    "cut_points",
    "project_by_group",
    "short_circuit",
    "toy_projection",
    "rules_w1",
    "closed_w2",
    "join_asof_view_before_purchase",
    "join_interval_cooccur",
    "session_baskets",
    "agg_cube_w7",
    "win_range_moving",
    "stream_session",
    "stream_sliding",
]


@pytest.fixture(scope="module")
def duck():
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    return c


def cells(df):
    df = df[sorted(df.columns)].astype(object)
    plain = lambda v: None if v is None or v is pd.NA or (isinstance(v, float) and math.isnan(v)) else round(float(v), 6) if isinstance(v, (int, float)) else v
    return sorted(tuple(map(repr, map(plain, r))) for r in df.itertuples(index=False))


@pytest.mark.parametrize("name", SOME)
def test_query_equals_sql(spark, duck, name):
    got, want = catalogue.queries()[name](spark, SF).toPandas(), duck.execute(catalogue.oracle_sql()[name]).fetchdf()
    assert sorted(got.columns) == sorted(want.columns) and cells(got) == cells(want)


def test_entry(spark):
    assert entry.entry(spark).count() > 0
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_scan_reads_only_what_is_asked(spark):
    plan = table(spark, SF, "lineitem", ["l_partkey"], "l_quantity > 45")._jdf.queryExecution().toString()
    assert "PushedFilters: [IsNotNull(l_quantity), GreaterThan(l_quantity,45.0)]" in plan and "ReadSchema: struct<l_partkey:bigint,l_quantity:double>" in plan


def test_ranked_counts_are_combined_before_the_shuffle(spark):
    from fimspark.operators import encode

    plan = encode.count_items(B.document_words(spark, SF))._jdf.queryExecution().toString()
    assert "partial_count" in plan


@pytest.mark.parametrize("fmt", ["text", "csv", "json", "orc"])
def test_formats(spark, tmp_path, fmt):
    tx = B.user_days(spark, "/root/testdata/sf0.001")
    write_baskets(tx, str(tmp_path / fmt), fmt)
    bag = lambda d: sorted("|".join(sorted(r["items"])) for r in d.collect())
    assert bag(read_baskets(spark, str(tmp_path / fmt), fmt)) == bag(tx)


def test_synthetic_rows_do_not_depend_on_partitions(spark):
    a = synth.baskets(spark, 200, 50, 8, 3)
    b = synth.baskets(spark, 400, 50, 8, 3).where("tid < 200").repartition(7)
    key = lambda d: sorted((r.tid, tuple(r["items"])) for r in d.collect())
    assert key(a) == key(b) and 4 < a.agg(F.avg(F.size("items"))).first()[0] < 10


def test_sql_surface(spark):
    tx = spark.createDataFrame([(1, ["a", "b"]), (2, ["a"]), (3, ["b", "c", "a"])], "tid long, items array<string>")
    sqlapi.register(spark, items=tx)
    got = {(r.itemset, r.support_count) for r in spark.sql("SELECT * FROM frequent_itemsets(TABLE(items) PARTITION BY (1), 2)").collect()}
    assert got == {("a", 3), ("b", 2), ("a|b", 2)}
    m = sqlapi.BudgetedItemsetMiner(2, 100, 0.6).fit(tx)
    assert {r.tid: r.prediction for r in m.transform(tx).collect()} == {1: [], 2: ["b"], 3: []}
    assert [r[0] for r in tx.orderBy("tid").select(sqlapi.is_subset("items", F.lit(["b"]))).collect()] == [True, False, True]


def test_null_and_empty_items_are_dropped(spark):
    rows = spark.createDataFrame([(1, "a"), (1, None), (1, ""), (2, None), (1, "a"), (None, "b")], "tid long, item string")
    assert {r.tid: r["items"] for r in B.from_long(rows).collect()} == {1: ["a"], None: ["b"]}


def test_asof_takes_only_earlier_rows(spark):
    a = spark.createDataFrame([(1, 5, "x"), (1, 1, "y"), (2, 9, "z")], "k long, t long, name string")
    b = spark.createDataFrame([(1, 1, 10), (1, 4, 40), (1, 5, 50)], "k long, t long, v long")
    assert {r.name: r.got for r in relops.asof(a, b, "k", "t", "v", "got").collect()} == {"x": 40, "y": None, "z": None}


def test_late_rows_are_dropped(spark, tmp_path):
    rows = lambda x: spark.createDataFrame(x, "event_id long, ts timestamp, user_id long, event_type string")
    import datetime as dt

    at = lambda d, h: dt.datetime(2024, 1, d, h)
    path = str(tmp_path / "events")
    rows([(1, at(1, 1), 1, "view"), (2, at(3, 1), 1, "view"), (2, at(3, 1), 1, "view")]).coalesce(1).write.parquet(path)
    events = spark.readStream.schema(spark.read.parquet(path).schema).parquet(path)
    sink, check = str(tmp_path / "out"), str(tmp_path / "check")
    run = lambda: S.item_counts(events, "1 day").writeStream.format("parquet").option("path", sink).option("checkpointLocation", check).trigger(availableNow=True).start().awaitTermination()
    run()
    rows([(3, at(1, 2), 1, "view"), (4, at(5, 1), 1, "view")]).coalesce(1).write.mode("append").parquet(path)  # the first is late by days
    run()
    rows([(5, at(9, 1), 1, "view")]).coalesce(1).write.mode("append").parquet(path)
    run()
    got = sorted((r.start, r.n) for r in spark.read.parquet(sink).collect())
    day = 86400
    first = int(dt.datetime(2024, 1, 1, tzinfo=dt.timezone.utc).timestamp())
    assert got == [(first, 1), (first + 2 * day, 2), (first + 4 * day, 1)]


def test_maintained_counts_report_crossings(spark, tmp_path):
    crossed = []
    S.maintain(S.events_source(spark, "/root/testdata/sf0.001/events.parquet"), str(tmp_path / "state"), lambda df: crossed.append(df.count()), min_count=3)
    assert crossed and crossed[0] > 0


@pytest.mark.parametrize("name", ["mine_budgeted_w3", "mine_budgeted_w4"])
def test_sets_of_any_size_are_mined(spark, name):
    """On the smallest tables nearly all sets of the ten suppliers are frequent."""
    got = {r["size"]: r["count"] for r in catalogue.queries()[name](spark, "/root/testdata/sf0.001").groupBy("size").count().collect()}
    assert [got.get(k) for k in range(1, 7)] == [10, 45, 120, 210, 252, 210]


def test_nested_loop_pairs_blocks(spark, monkeypatch):
    """Keys twice on either side, on one side only, and null; and the query's nested loop is over blocks."""
    monkeypatch.setattr(relops, "BLOCK_KEYS", 3)
    a = spark.createDataFrame([(k, v) for v, k in enumerate([1, 1, 2, 5, 7, 7, None, 40])], "k long, v int")
    b = spark.createDataFrame([(1, "x"), (1, "y"), (2, None), (7, "z"), (None, "n"), *((k, "o") for k in range(100, 120))], "j long, name string")
    bag = lambda d: sorted(map(str, d.select("k", "v", "j", "name").collect()))
    want = bag(a.join(b, a.k == b.j))
    assert bag(relops.join_blocks(a, b, "k", "j")) == want and len(want) == 7
    plan = catalogue.queries()["join_inner_shuffle_replicate_nl"](spark, SF)._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct (_a" in plan and "l_partkey" not in plan.split("CartesianProduct")[1].split("\n")[0]


@pytest.mark.parametrize("name", ["group_estimates", "run_ledger"])
def test_groups_that_no_task_can_hold_equal_sql(spark, duck, monkeypatch, name):
    """With a budget of a few hundred nodes, as with the usual one on larger tables, most groups are cut or become databases of their own."""
    usable = budget.usable_nodes(900)
    sql = catalogue.oracle_sql()[name].replace(str(catalogue._USABLE), str(usable))
    monkeypatch.setitem(catalogue.BUDGET, "w1", 900)
    monkeypatch.setattr(catalogue, "_USABLE", usable)
    got, want = catalogue.queries()[name](spark, SF).toPandas(), duck.execute(sql).fetchdf()
    assert sorted(got.columns) == sorted(want.columns) and cells(got) == cells(want)
