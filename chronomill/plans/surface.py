"""Relational surface around the temporal methods: guards, joins, aggregates, windows, sets, functions, stream windows."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import ticks
from ..operators import intervals as iv
from ..sources.store import table
from ..streaming.windows import session_spans, sliding_counts, tumbling_counts

_QUERIES: dict[str, Callable] = {}
_SQL: dict[str, str] = {}


def _query(sql: str):
    def keep(f):
        _QUERIES[f.__name__] = f
        _SQL[f.__name__] = sql
        return f

    return keep


def _events(spark, sf_dir) -> DataFrame:
    return table(spark, sf_dir, "events").select(F.col("event_id").alias("e"), F.col("user_id").alias("u"), F.col("event_type").alias("c"), "value", "props", "ts", ticks.seconds(F.col("ts")).alias("t"))


EV = "ev AS (SELECT event_id AS e, user_id AS u, event_type AS c, value, props, ts, floor(epoch(ts))::BIGINT AS t FROM events)"


@_query(f"WITH {EV} SELECT u, c, t FROM ev WHERE value > 30 AND c <> 'click'")
def guard_filter(spark, sf_dir):
    return _events(spark, sf_dir).filter("value > 30 AND c <> 'click'").select("u", "c", "t")


@_query("SELECT DISTINCT o_custkey AS c, o_orderpriority AS p FROM orders")
def project_recoalesce(spark, sf_dir):
    """A variable is dropped, so intervals of what is left are coalesced anew; on the whole span that is a distinct."""
    o = table(spark, sf_dir, "orders").select(F.col("o_custkey").alias("c"), F.col("o_orderpriority").alias("p"), F.lit(0).alias("lo"), F.lit(10).alias("hi"))
    return iv.coalesced(o).select("c", "p")


@_query("SELECT c_custkey AS c, n_name AS nation, r_name AS region FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey")
def join_natural(spark, sf_dir):
    c, n, r = (table(spark, sf_dir, t) for t in ("customer", "nation", "region"))
    return c.join(n, F.col("c_nationkey") == F.col("n_nationkey")).join(r, F.col("n_regionkey") == F.col("r_regionkey")).select(F.col("c_custkey").alias("c"), F.col("n_name").alias("nation"), F.col("r_name").alias("region"))


@_query("SELECT o_orderkey AS o FROM orders WHERE o_custkey IN (SELECT c_custkey FROM customer WHERE c_nationkey = 3)")
def join_semi_delta(spark, sf_dir):
    delta = table(spark, sf_dir, "customer").filter("c_nationkey = 3").select(F.col("c_custkey").alias("o_custkey"))
    return table(spark, sf_dir, "orders").join(delta, "o_custkey", "left_semi").select(F.col("o_orderkey").alias("o"))


@_query("SELECT c_custkey AS c FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")
def join_anti_atoms(spark, sf_dir):
    return table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("c")).join(table(spark, sf_dir, "orders").select(F.col("o_custkey").alias("c")), "c", "left_anti")


@_query(f"WITH {EV}, x AS (SELECT e, t, t + 600 AS z FROM ev WHERE c = 'purchase'), y AS (SELECT e, t, t + 600 AS z FROM ev WHERE c = 'view') SELECT x.e AS p, y.e AS v FROM x JOIN y ON x.t <= y.z AND y.t <= x.z")
def join_theta_buckets(spark, sf_dir):
    ev = _events(spark, sf_dir)
    side = lambda c, n: ev.filter(F.col("c") == c).select(F.col("e").alias(n), (2 * F.col("t")).alias("lo"), (2 * (F.col("t") + 600)).alias("hi"))
    return iv.overlap_join(side("purchase", "p"), side("view", "v"), [], bucket=2400).select("p", "v")


@_query("SELECT o_orderstatus AS status, o_orderpriority AS priority, count(*) AS n FROM orders GROUP BY ROLLUP (o_orderstatus, o_orderpriority)")
def agg_rollup_facts(spark, sf_dir):
    return table(spark, sf_dir, "orders").select(F.col("o_orderstatus").alias("status"), F.col("o_orderpriority").alias("priority")).rollup("status", "priority").agg(F.count(F.lit(1)).alias("n"))


@_query("SELECT l_returnflag AS flag, l_linestatus AS status, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
def agg_cube_status(spark, sf_dir):
    return table(spark, sf_dir, "lineitem").select(F.col("l_returnflag").alias("flag"), F.col("l_linestatus").alias("status")).cube("flag", "status").agg(F.count(F.lit(1)).alias("n"))


@_query("SELECT user_id AS u, event_type AS c, count(*) AS n FROM events GROUP BY GROUPING SETS ((user_id), (event_type))")
def agg_grouping_sets(spark, sf_dir):
    _events(spark, sf_dir).select("u", "c").createOrReplaceTempView("ags_events")
    return spark.sql("SELECT u, c, count(*) AS n FROM ags_events GROUP BY GROUPING SETS ((u), (c))")


@_query("SELECT event_type AS c, count(DISTINCT user_id) AS users FROM events GROUP BY event_type")
def agg_distinct_atoms(spark, sf_dir):
    return _events(spark, sf_dir).groupBy("c").agg(F.countDistinct("u").alias("users"))


@_query(f"WITH {EV} SELECT e, t - lag(t) OVER (PARTITION BY u ORDER BY t, e) AS gap FROM ev")
def win_lag_gaps(spark, sf_dir):
    return _events(spark, sf_dir).select("e", (F.col("t") - F.lag("t").over(Window.partitionBy("u").orderBy("t", "e"))).alias("gap"))


@_query(f"WITH {EV} SELECT e, count(*) OVER (PARTITION BY u ORDER BY t RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW) AS recent FROM ev")
def win_range_count(spark, sf_dir):
    return _events(spark, sf_dir).select("e", F.count(F.lit(1)).over(Window.partitionBy("u").orderBy("t").rangeBetween(-86400, 0)).alias("recent"))


@_query("SELECT c, u, n, r FROM (SELECT event_type AS c, user_id AS u, count(*) AS n, rank() OVER (PARTITION BY event_type ORDER BY count(*) DESC, user_id)::INTEGER AS r FROM events GROUP BY event_type, user_id) WHERE r <= 5")
def win_rank_active(spark, sf_dir):
    n = _events(spark, sf_dir).groupBy("c", "u").agg(F.count(F.lit(1)).alias("n"))
    return n.withColumn("r", F.rank().over(Window.partitionBy("c").orderBy(F.desc("n"), "u"))).filter("r <= 5")


@_query("SELECT u, lo, hi FROM (SELECT user_id AS u, min(floor(epoch(ts)))::BIGINT AS lo, max(floor(epoch(ts)))::BIGINT AS hi FROM events GROUP BY user_id) ORDER BY hi - lo DESC, u LIMIT 10")
def topk_longest(spark, sf_dir):
    spans = _events(spark, sf_dir).groupBy("u").agg(F.min("t").alias("lo"), F.max("t").alias("hi"))
    return spans.orderBy(F.desc(F.col("hi") - F.col("lo")), "u").limit(10)


_SETS = "SELECT DISTINCT user_id AS u FROM events WHERE event_type = '{}' AND value > 60"


def _two(spark, sf_dir):
    ev = _events(spark, sf_dir).filter("value > 60")
    return ev.filter("c = 'view'").select("u"), ev.filter("c = 'click'").select("u")


@_query(f"{_SETS.format('view')} UNION {_SETS.format('click')}")
def set_union(spark, sf_dir):
    a, b = _two(spark, sf_dir)
    return a.union(b).distinct()


@_query(f"{_SETS.format('view')} INTERSECT {_SETS.format('click')}")
def set_intersect(spark, sf_dir):
    a, b = _two(spark, sf_dir)
    return a.intersect(b)


@_query(f"{_SETS.format('view')} EXCEPT {_SETS.format('click')}")
def set_except(spark, sf_dir):
    a, b = _two(spark, sf_dir)
    return a.distinct().exceptAll(b.distinct())


@_query(f"WITH {EV} SELECT e, t, (t // 86400)::BIGINT AS day, date_trunc('second', ts) AS back FROM ev")
def fn_time_roundtrip(spark, sf_dir):
    return _events(spark, sf_dir).select("e", "t", ticks.days(F.col("ts")).alias("day"), ticks.from_seconds(F.col("t")).alias("back"))


@_query(f"WITH {EV} SELECT e, (props->>'k')::INTEGER AS k FROM ev WHERE (props->>'k')::INTEGER > 50")
def fn_json_guard(spark, sf_dir):
    return _events(spark, sf_dir).select("e", F.get_json_object("props", "$.k").cast("int").alias("k")).filter("k > 50")


@_query("SELECT o_custkey AS c, count(*)::INTEGER AS n, min(epoch(o_orderdate)::BIGINT // 86400)::BIGINT AS first_day, sum(epoch(o_orderdate)::BIGINT // 86400)::BIGINT AS total FROM orders GROUP BY o_custkey")
def fn_array_pack(spark, sf_dir):
    o = table(spark, sf_dir, "orders").select(F.col("o_custkey").alias("c"), ticks.days(F.col("o_orderdate")).alias("d"))
    packed = o.groupBy("c").agg(F.sort_array(F.collect_list("d")).alias("ds"))
    return packed.select("c", F.size("ds").alias("n"), F.col("ds")[0].alias("first_day"), F.aggregate("ds", F.lit(0).cast("long"), lambda a, x: a + x).alias("total"))


@_query("SELECT conv_id AS c, turn, '[' || turn || ',' || (turn + 1) || ')' AS shown FROM conversations")
def fn_render(spark, sf_dir):
    lo, hi = 2 * F.col("turn"), 2 * (F.col("turn") + 1) - 1
    start = F.concat(F.when(F.pmod(lo, F.lit(2)) == 1, "(").otherwise("["), F.floor(lo / 2).cast("string"))
    end = F.concat(F.floor((hi + 1) / 2).cast("string"), F.when(F.pmod(hi, F.lit(2)) == 1, ")").otherwise("]"))
    return table(spark, sf_dir, "conversations").select(F.col("conv_id").alias("c"), "turn", F.concat_ws(",", start, end).alias("shown"))


@_query("SELECT d.lang, count(*) AS n, count_if(l.toxic = 1) AS toxic FROM documents d JOIN labels l ON d.doc_id = l.doc_id GROUP BY d.lang")
def rigid_classes(spark, sf_dir):
    """Timeless classes of documents joined by key."""
    return table(spark, sf_dir, "documents").select("doc_id", "lang").join(table(spark, sf_dir, "labels"), "doc_id").groupBy("lang").agg(F.count(F.lit(1)).alias("n"), F.count_if(F.col("toxic") == 1).alias("toxic"))


@_query("SELECT event_type AS c, floor(epoch(ts) / 3600)::BIGINT * 3600 AS start_t, count(*) AS n, round(sum(value), 2) AS total FROM events GROUP BY ALL")
def stream_tumbling(spark, sf_dir):
    out = tumbling_counts(table(spark, sf_dir, "events"), "1 hour")
    return out.select("c", ticks.seconds(F.col("start")).alias("start_t"), "n", F.round("total", 2).alias("total"))


@_query("SELECT event_type AS c, s AS start_t, count(*) AS n FROM (SELECT event_type, unnest(generate_series((floor(epoch(ts) / 1800)::BIGINT - 1) * 1800, floor(epoch(ts) / 1800)::BIGINT * 1800, 1800)) AS s FROM events) GROUP BY ALL")
def stream_sliding(spark, sf_dir):
    return sliding_counts(table(spark, sf_dir, "events"), "1 hour", "30 minutes").select("c", ticks.seconds(F.col("start")).alias("start_t"), "n")


@_query("WITH e AS (SELECT user_id AS u, ts, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 4 HOUR THEN 0 ELSE 1 END AS o FROM events), g AS (SELECT u, ts, sum(o) OVER (PARTITION BY u ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM e) SELECT u, count(*) AS n, floor(epoch(min(ts)))::BIGINT AS start_t FROM g GROUP BY u, s")
def stream_session(spark, sf_dir):
    return session_spans(table(spark, sf_dir, "events"), "4 hours").select("u", "n", ticks.seconds(F.col("start")).alias("start_t"))


def queries() -> dict:
    return _QUERIES


def oracle_sql() -> dict[str, str]:
    return _SQL
