"""Queries over whole tables, on small tables of their own."""

import datetime as dt

from pyspark.sql import functions as F

import __spark_entry__ as entry

DAY0 = dt.date(2024, 1, 1)


def written(spark, path, **tables):
    for name, (schema, rows) in tables.items():
        spark.createDataFrame(rows, schema).write.parquet(f"{path}/{name}.parquet")
    return str(path)


def test_reach_has_paths_of_any_length(spark, tmp_path):
    n = 12
    sf = written(
        spark,
        tmp_path,
        orders=("o_orderkey int, o_custkey int, o_orderdate date", [(i, i, DAY0) for i in range(n)]),
        customer=("c_custkey int, c_nationkey int", [(i, i) for i in range(n)]),
        supplier=("s_suppkey int, s_nationkey int", [(i, i) for i in range(n + 1)]),
        lineitem=("l_orderkey int, l_suppkey int, l_shipdate date", [(i, i + 1, DAY0) for i in range(n)]),
    )
    got = [tuple(r) for r in entry.queries()["recursive_reach"](spark, sf).select("n", "m").collect()]
    assert sorted(got) == [(a, b) for a in range(n) for b in range(a + 1, n + 1)]


def test_as_of_takes_every_line(spark):
    sf = "/root/testdata/sf0.001"
    day = lambda c: F.datediff(F.col(c).cast("date"), F.lit("1970-01-01").cast("date"))
    orders = [tuple(r) for r in spark.read.parquet(f"{sf}/orders.parquet").select("o_orderkey", "o_custkey", day("o_orderdate")).collect()]
    lines = [tuple(r) for r in spark.read.parquet(f"{sf}/lineitem.parquet").select("l_orderkey", "l_linenumber", day("l_shipdate")).collect()]
    customer = {o: c for o, c, _ in orders}
    dates = {}
    for _, c, d in orders:
        dates.setdefault(c, []).append(d)
    want = [(customer[o], o, line, d, max((x for x in dates[customer[o]] if x <= d), default=-1)) for o, line, d in lines if o in customer]
    got = entry.queries()["as_of_lines"](spark, sf).fillna(-1, ["last_order"]).collect()
    assert sorted(map(tuple, got)) == sorted(want)
    assert {r[2] for r in got} > {1}


def test_inspection_queries_follow_the_tables(spark, tmp_path):
    """The algebra of periodic models, the statistics and the rule table are of the given tables, not of made-up rows."""
    at = lambda day: dt.datetime(2024, 1, 1 + day, 7)
    events = [(1, 0, "view", 120.0, at(3)), (2, 0, "view", 10.0, at(4)), (3, 0, "click", 80.0, at(1)), (4, 1, "view", 0.0, at(5)), (5, 2, "click", 31.0, at(2)), (6, 2, "purchase", 1.0, at(0))]
    sf = written(
        spark,
        tmp_path,
        events=("event_id long, user_id long, event_type string, value double, ts timestamp_ntz, props string", [(*e, None) for e in events]),
        orders=("o_orderkey long, o_custkey long, o_orderdate date, o_orderpriority string, o_orderstatus string", [(i, i % 2, DAY0, "hl"[i % 2], "F") for i in range(5)]),
        lineitem=("l_orderkey long, l_partkey long, l_suppkey long, l_shipdate date", [(i, 0, 0, DAY0) for i in range(7)]),
        customer=("c_custkey long, c_nationkey int, c_mktsegment string", [(0, 1, "a"), (1, 1, "b")]),
        supplier=("s_suppkey long, s_nationkey int", [(0, 0), (1, 2), (2, 0)]),
        part=("p_partkey long, p_type string", [(0, "t")]),
        nation=("n_nationkey int, n_regionkey int", [(i, 0) for i in range(4)]),
    )
    run = lambda name: entry.queries()[name](spark, sf).collect()
    points = lambda name: {(r["x"], r["start_t"]) for r in run(name)}
    two = {(0, t) for t in range(3, 71, 2)} | {(1, t) for t in range(5, 71, 2)}
    three = {(0, t) for t in range(1, 71, 3)} | {(2, t) for t in range(2, 71, 3)}
    assert points("pm_union") == two | three
    assert points("pm_minus") == two - three
    assert [tuple(r) for r in run("pm_lcm")] == [(6,)]
    assert [tuple(r) for r in run("pm_align")] == [(2 * 12 + 1,)]
    facts = {r["workload"]: r["facts"] for r in run("dataset_stats")}
    assert facts == {"example": 2, "fault": 3 + 2 + 3 + 2, "meteo": 6 + 1 + 2, "generated": 5, "trade": 3 * 5 + 7 + 2 * 2 + 1 + 3 + 4}
    rules = run("rule_table")
    assert len(rules) == 85
    by_head = {(r["head"], r["needs"]): r["facts"] for r in rules}
    assert by_head["urgent_0", "ordered,prio_0"] == 5 + 3 and by_head["bought_from", "contains,ordered"] == 5 + 7 and by_head["steady", "watch"] == 0
