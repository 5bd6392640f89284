"""Queries of the temporal engine, and DuckDB SQL for each that SQL can express."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import cells
from ..functions.cells import Range
from ..operators import intervals as iv
from ..sources.store import facts_of, stored, union_all
from . import maintain as mt
from . import periodic as pr
from . import surface
from . import workloads as wl
from .evaluate import ATOM, Evaluator, bounds, horizon_model
from .rules import parse_program, program_rows

H = 3600
Query = Callable[[SparkSession, str], DataFrame]
_QUERIES: dict[str, Query] = {}
_SQL: dict[str, str] = {}


def query(sql: str | None = None, name: str | None = None):
    def keep(f: Query) -> Query:
        key = name or f.__name__
        _QUERIES[key] = f
        if sql is not None:
            _SQL[key] = sql
        return f

    return keep


# Pieces of oracle SQL. Relations are (keys, lo, hi) in half units: instants even, open gaps odd.

EV = "ev AS (SELECT user_id AS u, event_type AS c, value, floor(epoch(ts))::BIGINT AS t FROM events)"
VIEWS = f"{EV}, a AS (SELECT u, 2 * t AS lo, 2 * (t + 86400) AS hi FROM ev WHERE c = 'view'), b AS (SELECT u, 2 * t AS lo, 2 * (t + 43200) - 1 AS hi FROM ev WHERE c = 'click')"


def sql_coalesced(source: str, keys: str) -> str:
    by = f"PARTITION BY {keys} ORDER BY lo, hi"
    return f"""(SELECT {keys}, min(lo) AS lo, max(hi) AS hi FROM (SELECT *, sum(opens) OVER ({by} ROWS UNBOUNDED PRECEDING) AS island FROM (
      SELECT {keys}, lo, hi, CASE WHEN lo <= max(hi) OVER ({by} ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) + 1 THEN 0 ELSE 1 END AS opens FROM {source})) GROUP BY {keys}, island)"""


def sql_swept(a: str, b: str, keep: str, keys: str) -> str:
    test = {"intersect": "p AND q", "union": "p OR q", "minus": "p AND NOT q", "symdiff": "p <> q"}[keep]
    ends = f"""SELECT {keys}, pos, sum(x) AS x, sum(y) AS y FROM (
      SELECT {keys}, lo AS pos, 1 AS x, 0 AS y FROM {a} UNION ALL SELECT {keys}, hi + 1, -1, 0 FROM {a} UNION ALL SELECT {keys}, lo, 0, 1 FROM {b} UNION ALL SELECT {keys}, hi + 1, 0, -1 FROM {b}) GROUP BY {keys}, pos"""
    by = f"OVER (PARTITION BY {keys} ORDER BY pos)"
    return sql_coalesced(f"(SELECT {keys}, pos AS lo, nxt - 1 AS hi FROM (SELECT {keys}, pos, lead(pos) {by} AS nxt, sum(x) {by} > 0 AS p, sum(y) {by} > 0 AS q FROM ({ends})) WHERE nxt IS NOT NULL AND ({test}))", keys)


def sql_shown(source: str, columns: str) -> str:
    # Halves below zero are rounded down.
    return f"SELECT {columns}, floor(lo / 2.0)::BIGINT AS start_t, lo % 2 <> 0 AS start_open, floor((hi + 1) / 2.0)::BIGINT AS end_t, hi % 2 <> 0 AS end_open FROM {source}"


def shown(df: DataFrame, *columns) -> DataFrame:
    return df.select(*columns, *cells.rendered())


def user_views(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    ev = wl.events(spark, sf_dir)
    a = ev.filter("c = 'view'").select("u", (2 * F.col("t")).alias("lo"), (2 * (F.col("t") + 86400)).alias("hi"))
    b = ev.filter("c = 'click'").select("u", (2 * F.col("t")).alias("lo"), (2 * (F.col("t") + 43200) - 1).alias("hi"))
    return a, b


# Kernels.


@query(f"WITH {VIEWS} " + sql_shown(sql_coalesced("a", "u"), "u"))
def coalesce_events(spark, sf_dir):
    return shown(iv.coalesced(user_views(spark, sf_dir)[0]), "u")


@query(f"WITH {VIEWS} " + sql_shown(sql_coalesced("b", "u"), "u"))
def coalesce_in_slices(spark, sf_dir):
    return shown(iv.coalesced_in_slices(user_views(spark, sf_dir)[1], 5 * 86400), "u")


for _keep in ("union", "intersect", "minus"):

    def _swept(spark, sf_dir, keep=_keep):
        return shown(iv.sweep(*user_views(spark, sf_dir), keep), "u")

    query(f"WITH {VIEWS} " + sql_shown(sql_swept("a", "b", _keep, "u"), "u"), f"t_{_keep}")(_swept)


@query(f"WITH {VIEWS}, d AS {sql_swept('b', 'a', 'minus', 'u')} SELECT u, u NOT IN (SELECT u FROM d) AS contained FROM (SELECT DISTINCT u FROM b)")
def t_contains(spark, sf_dir):
    a, b = user_views(spark, sf_dir)
    rest = iv.sweep(b, a, "minus").groupBy("u").agg(F.count(F.lit(1)).alias("n"))
    return b.select("u").distinct().join(rest, "u", "left").select("u", F.col("n").isNull().alias("contained"))


_SPAN = (2 * 1_704_067_200, 2 * 1_706_745_600)


@query(f"WITH {VIEWS}, w AS (SELECT DISTINCT u, {_SPAN[0]} AS lo, {_SPAN[1]} AS hi FROM a) " + sql_shown(sql_swept("w", "a", "minus", "u"), "u"))
def complement(spark, sf_dir):
    return shown(iv.complement(user_views(spark, sf_dir)[0], *_SPAN), "u")


@query(f"WITH {VIEWS}, w AS (SELECT DISTINCT u, {_SPAN[0]} AS lo, {_SPAN[1]} AS hi FROM a), g AS {sql_swept('w', 'a', 'minus', 'u')} " + sql_shown("(SELECT * FROM g WHERE hi - lo + 1 >= 86400)", "u"))
def gaps(spark, sf_dir):
    return shown(iv.gaps(user_views(spark, sf_dir)[0], *_SPAN, least=86400), "u")


@query(f"WITH {VIEWS}, x AS {sql_coalesced('a', 'u')} SELECT u, count(*) AS intervals, sum(hi - lo + 1)::BIGINT AS cells FROM x GROUP BY u")
def duration_by_atom(spark, sf_dir):
    return iv.durations(user_views(spark, sf_dir)[0])


@query(f"WITH {VIEWS}, x AS {sql_coalesced('a', 'u')} SELECT u, count(*)::INTEGER AS n, min(lo) AS first_lo, max(hi) AS last_hi FROM x GROUP BY u")
def packed_sets(spark, sf_dir):
    p = iv.packed(iv.coalesced(user_views(spark, sf_dir)[0]))
    return iv.packed(iv.unpacked(p)).select("u", F.size("set").alias("n"), F.col("set")[0]["lo"].alias("first_lo"), F.element_at("set", -1)["hi"].alias("last_hi"))


@query(f"WITH {VIEWS}, x AS {sql_coalesced('a', 'u')}, y AS {sql_coalesced('b', 'u')} " + sql_shown("(SELECT x.u, greatest(x.lo, y.lo) AS lo, least(x.hi, y.hi) AS hi FROM x JOIN y ON x.u = y.u AND x.lo <= y.hi AND y.lo <= x.hi)", "u"))
def interval_join(spark, sf_dir):
    a, b = user_views(spark, sf_dir)
    return shown(iv.overlap_join(iv.coalesced(a), iv.coalesced(b), ["u"]), "u")


@query("WITH q AS (SELECT o_custkey AS c, l_orderkey AS o, l_linenumber AS line, l_shipdate::DATE AS d FROM lineitem JOIN orders ON l_orderkey = o_orderkey), v AS (SELECT DISTINCT o_custkey AS c, o_orderdate::DATE AS d FROM orders) SELECT q.c, q.o, q.line, date_diff('day', DATE '1970-01-01', q.d)::BIGINT AS ship, date_diff('day', DATE '1970-01-01', v.d)::BIGINT AS last_order FROM q ASOF LEFT JOIN v ON q.c = v.c AND q.d >= v.d")
def as_of_lines(spark, sf_dir):
    orders = wl.table(spark, sf_dir, "orders").select(F.col("o_custkey").alias("c"), F.col("o_orderkey").alias("o"), wl.ticks.days(F.col("o_orderdate")).alias("at"))
    lines = wl.table(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("o"), F.col("l_linenumber").alias("line"), wl.ticks.days(F.col("l_shipdate")).alias("at"))
    probes = lines.join(orders.select("o", "c"), "o")
    values = orders.select("c", "at", F.col("at").alias("last_order"))
    return iv.as_of(values, probes, ["c"], "last_order").select("c", "o", "line", F.col("at").alias("ship"), "last_order")


_MID = (2 * 1_704_500_000, 2 * 1_705_500_000)


@query(f"WITH {VIEWS}, x AS {sql_coalesced('a', 'u')} " + sql_shown(f"(SELECT u, greatest(lo, {_MID[0]}) AS lo, least(hi, {_MID[1]}) AS hi FROM x WHERE hi >= {_MID[0]} AND lo <= {_MID[1]})", "u"))
def clip_window(spark, sf_dir):
    return shown(iv.clipped(iv.coalesced(user_views(spark, sf_dir)[0]), *_MID), "u")


@query(f"WITH {VIEWS}, x AS {sql_coalesced('b', 'u')} " + sql_shown(f"(SELECT u, lo + {2 * H} AS lo, hi + {2 * H} AS hi FROM x)", "u"))
def shift_facts(spark, sf_dir):
    return shown(iv.shifted(iv.coalesced(user_views(spark, sf_dir)[1]), 2 * H), "u")


# Operators, through rules.


def _by_rule(rule: str):
    def run(spark, sf_dir):
        a, b = user_views(spark, sf_dir)
        rename = lambda df, p: iv.coalesced(df).select(F.lit(p).alias("pred"), F.col("u").cast("string").alias("a0"), F.lit("").alias("a1"), F.lit("").alias("a2"), "lo", "hi")
        at = wl.facts_at(wl.events(spark, sf_dir).filter("c = 'click'"), "tap", ["u"], F.col("t"))
        out = Evaluator(parse_program(rule)).applied(union_all([rename(a, "view"), rename(b, "click"), at]))
        return shown(out, F.col("a0").cast("long").alias("u"))

    return run


def _moved(source: str, lo: int, hi: int) -> str:
    return f"(SELECT u, lo + {2 * lo} AS lo, hi + {2 * hi} AS hi FROM {sql_coalesced(source, 'u')} WHERE lo + {2 * lo} <= hi + {2 * hi})"


_OPS = {
    "op_past_some": (f"out(u) :- PAST_SOME[{H},{2 * H}] view(u).", _moved("a", H, 2 * H)),
    "op_next_some": (f"out(u) :- NEXT_SOME[{H},{2 * H}] click(u).", _moved("b", -2 * H, -H)),
    "op_past_all": (f"out(u) :- PAST_ALL[0,{12 * H}] view(u).", _moved("a", 12 * H, 0)),
    "op_next_all": (f"out(u) :- NEXT_ALL[{H},{3 * H}] click(u).", _moved("b", -H, -3 * H)),
    "op_nested": (f"out(u) :- PAST_ALL[0,{24 * H}] PAST_SOME[0,{12 * H}] view(u).", f"(SELECT u, lo + {48 * H} AS lo, hi AS hi FROM {sql_coalesced('(SELECT u, lo, hi + ' + str(24 * H) + ' AS hi FROM a)', 'u')} WHERE lo + {48 * H} <= hi)"),
    "body_conjunction": ("out(u) :- view(u), click(u).", sql_swept("a", "b", "intersect", "u")),
    "head_always": (f"NEXT_ALL[{H},{2 * H}] PAST_ALL[0,{H}] out(u) :- click(u).", _moved("b", 0, 2 * H)),
    "op_since": (f"out(u) :- view(u) SINCE[0,{2 * H}] tap(u).", f"(SELECT u, lo, hi FROM tap UNION ALL SELECT x.u, tap.lo, least(tap.lo + {4 * H}, x.hi) FROM {sql_coalesced('a', 'u')} x JOIN tap ON x.u = tap.u AND tap.lo BETWEEN x.lo AND x.hi)"),
    "op_until": (f"out(u) :- view(u) UNTIL[{H},{2 * H}] tap(u).", f"(SELECT x.u, greatest(tap.lo - {4 * H}, x.lo) AS lo, tap.lo - {2 * H} AS hi FROM {sql_coalesced('a', 'u')} x JOIN tap ON x.u = tap.u AND tap.lo BETWEEN x.lo AND x.hi WHERE tap.lo - {2 * H} >= x.lo)"),
}
for _name, (_rule, _source) in _OPS.items():
    query(f"WITH {VIEWS}, tap AS (SELECT u, lo, lo AS hi FROM b) " + sql_shown(sql_coalesced(_source, "u"), "u"), _name)(_by_rule(_rule))


# Applications of all rules.

_METEO_FACTS = f"""{EV}, hi AS {sql_coalesced("(SELECT u, 2 * t AS lo, 2 * (t + 43200) AS hi FROM ev WHERE value > 100)", "u")},
 span AS (SELECT 2 * min(t) AS lo, 2 * (max(t) + 86400) AS hi FROM ev), home AS (SELECT c_custkey AS u, c_nationkey AS n FROM customer WHERE c_custkey IN (SELECT u FROM ev))"""


def meteo_sql(readings: str = "hi", facts: str = _METEO_FACTS) -> str:
    """The four derived relations from coalesced readings."""
    wave = f"(SELECT u, lo + 43200 AS lo, hi FROM {readings} WHERE lo + 43200 <= hi)"
    alert = sql_coalesced(f"(SELECT u, lo, hi + 172800 AS hi FROM {wave})", "u")
    zone = sql_coalesced(f"(SELECT n, greatest(r.lo, span.lo) AS lo, least(r.hi, span.hi) AS hi FROM {readings} r JOIN home ON r.u = home.u CROSS JOIN span WHERE greatest(r.lo, span.lo) <= least(r.hi, span.hi))", "n")
    return f"WITH {facts}, m AS (SELECT 'hot' AS pred, u AS x, lo, hi FROM {readings} UNION ALL SELECT 'wave', u, lo, hi FROM {wave} UNION ALL SELECT 'alert', u, lo, hi FROM {alert} UNION ALL SELECT 'zone_hot', n, lo, hi FROM {zone}) " + sql_shown("m", "pred, x")


def derived(pm: pr.PeriodicModel, preds: tuple[str, ...], *columns) -> DataFrame:
    return shown(pm.core.filter(F.col("pred").isin(*preds)), *(columns or ("pred", F.col("a0").cast("long").alias("x"))))


METEO_HEADS = ("hot", "zone_hot", "wave", "alert")


@query(f"WITH {_METEO_FACTS} " + sql_shown("(SELECT 'hot' AS pred, u AS x, lo, hi FROM hi)", "pred, x"))
def one_step(spark, sf_dir):
    w = wl.meteo(spark, sf_dir)
    out = Evaluator(w.program).consequence(iv.coalesced(w.explicit, ATOM))
    return shown(out.filter(F.col("pred").isin(*METEO_HEADS)), "pred", F.col("a0").cast("long").alias("x"))


@query(meteo_sql())
def k_steps(spark, sf_dir):
    """The third stage of iterated application: all there is for these rules."""
    w = wl.meteo(spark, sf_dir)
    ev, facts = Evaluator(w.program), stored(iv.coalesced(w.explicit, ATOM), "facts")
    for _ in range(3):
        facts = stored(ev.consequence(facts), "facts")
    return shown(facts.filter(F.col("pred").isin(*METEO_HEADS)), "pred", F.col("a0").cast("long").alias("x"))


@query("WITH RECURSIVE e AS (SELECT DISTINCT c_nationkey AS n, s_nationkey AS m FROM orders JOIN customer ON o_custkey = c_custkey JOIN lineitem ON l_orderkey = o_orderkey JOIN supplier ON l_suppkey = s_suppkey WHERE l_shipdate::DATE BETWEEN o_orderdate::DATE AND o_orderdate::DATE + 3), r AS (SELECT n, m FROM e UNION SELECT r.n, e.m FROM r JOIN e ON r.m = e.n) SELECT n, m FROM r")
def recursive_reach(spark, sf_dir):
    """Nations reachable through trade, in rounds that double the paths until no pair is new."""
    for t in ("orders", "customer", "lineitem", "supplier"):
        wl.table(spark, sf_dir, t).createOrReplaceTempView(f"rr_{t}")
    edges = spark.sql("""SELECT DISTINCT CAST(c_nationkey AS INT) AS n, CAST(s_nationkey AS INT) AS m FROM rr_orders JOIN rr_customer ON o_custkey = c_custkey JOIN rr_lineitem ON l_orderkey = o_orderkey JOIN rr_supplier ON l_suppkey = s_suppkey
      WHERE CAST(l_shipdate AS DATE) BETWEEN CAST(o_orderdate AS DATE) AND date_add(CAST(o_orderdate AS DATE), 3)""")
    reach = stored(edges, "reach")
    known, pairs = -1, reach.count()
    while pairs > known:
        longer = reach.withColumnRenamed("m", "k").join(reach.withColumnRenamed("n", "k"), "k").select("n", "m")
        reach = stored(reach.unionByName(longer).distinct(), "reach")
        known, pairs = pairs, reach.count()
    return reach


# Example workload: closed forms.


def example_sql(keys: str, last: int = 100) -> str:
    return f"WITH k AS ({keys}) SELECT s_suppkey AS x, g.j AS start_t, false AS start_open, least(g.j + 1, {last})::BIGINT AS end_t, false AS end_open FROM k CROSS JOIN (SELECT unnest(generate_series(0, {last}, 10))::BIGINT AS j) g"


def _x():
    return F.col("a0").cast("long").alias("x")

_BEFORE = "SELECT s_suppkey FROM supplier WHERE s_suppkey < (SELECT max(s_suppkey) FROM supplier)"
_AFTER = "SELECT s_suppkey FROM supplier WHERE s_suppkey > (SELECT min(s_suppkey) FROM supplier)"


@query(example_sql(_BEFORE))
def horizon_wex(spark, sf_dir):
    w = wl.example(spark, sf_dir)
    return shown(iv.clipped(horizon_model(w.program, w.explicit, -100, 200, lambda d: stored(d, "horizon")), -100, 200), _x())


@query(example_sql(_BEFORE))
def rebuild_wex(spark, sf_dir):
    return shown(pr.expanded(wl.built(spark, sf_dir, "example")[1], -100, 200), _x())


@query(example_sql(_BEFORE, 1000).replace("least(g.j + 1, 1000)", "g.j + 1").replace("generate_series(0, 1000, 10)", "generate_series(900, 990, 10)"))
def expand_window(spark, sf_dir):
    return shown(pr.expanded(wl.built(spark, sf_dir, "example")[1], 1800, 1998), _x())


@query("SELECT 'right' AS side, 10::BIGINT AS length, 11 AS depth")
def find_periods(spark, sf_dir):
    w, pm = wl.built(spark, sf_dir, "example")
    rows = [(s, p.length) for s, p in (("left", pm.left), ("right", pm.right)) if p]
    return spark.createDataFrame(rows, "side string, length long").withColumn("depth", F.lit(w.program.depth))


def example_changes(spark, sf_dir) -> tuple[DataFrame, DataFrame]:
    lo, hi = wl.table(spark, sf_dir, "supplier").agg(F.min("s_suppkey"), F.max("s_suppkey")).first()
    return facts_of(spark, [("r", [lo], 0, 1)]), facts_of(spark, [("r", [hi], 0, 1)])


@query(example_sql(_AFTER))
def maintain_wex(spark, sf_dir):
    w, pm = wl.built(spark, sf_dir, "example")
    _, out, _ = mt.maintain(w.program, w.explicit, pm, *example_changes(spark, sf_dir))
    return shown(pr.expanded(out, -100, 200), _x())


@query(example_sql("SELECT min(s_suppkey) AS s_suppkey FROM supplier"))
def retract_wex(spark, sf_dir):
    w, pm = wl.built(spark, sf_dir, "example")
    gone = mt.retract(w.program, pm, example_changes(spark, sf_dir)[0], bounds(w.explicit), mt.Options(), mt.StageStats())
    return shown(pr.expanded(gone, -100, 200), _x())


@query(example_sql("SELECT max(s_suppkey) AS s_suppkey FROM supplier"))
def extend_wex(spark, sf_dir):
    w, pm = wl.built(spark, sf_dir, "example")
    new = mt.extend(w.program, pm, mt.bounded(example_changes(spark, sf_dir)[1]), bounds(w.explicit), mt.Options(), mt.StageStats())
    return shown(pr.expanded(new, -100, 200), _x())


def _phase_models(spark, sf_dir) -> tuple[pr.PeriodicModel, pr.PeriodicModel]:
    """p(u) every second day from a user's first view on, and every third from the first click on; the second model's
    period opens later."""
    ev = wl.events(spark, sf_dir).filter("c IN ('view', 'click')")
    first = stored(ev.select("u", "c", F.floor((F.col("t") - F.lit(1_704_067_200)) / wl.DAY).cast("long").alias("d")).groupBy("u", "c").agg(F.min("d").alias("d")), "first")
    out = []
    for c, n, later in (("view", 2, 0), ("click", 3, 10)):
        own = first.filter(F.col("c") == c)
        last = (own.agg(F.max("d")).first()[0] or 0) + later
        days = own.select("u", F.explode(F.sequence("d", F.lit(last + n), F.lit(n).cast("long"))).alias("d"))
        out.append(pr.PeriodicModel(wl.facts_at(days, "p", ["u"], F.col("d")), None, pr.Period(2 * last + 1, 2 * (last + n))))
    return out[0], out[1]


_PHASES = f"WITH {EV}, f AS (SELECT u, c, min(floor((t - 1704067200) / 86400.0))::BIGINT AS d FROM ev WHERE u IS NOT NULL AND c IN ('view', 'click') GROUP BY u, c), two AS (SELECT u AS x, unnest(generate_series(d, 70, 2))::BIGINT AS t FROM f WHERE c = 'view'), three AS (SELECT u AS x, unnest(generate_series(d, 70, 3))::BIGINT AS t FROM f WHERE c = 'click') "
_POINTS = "SELECT x, t AS start_t, false AS start_open, t AS end_t, false AS end_open FROM "


@query(_PHASES + _POINTS + "(FROM two UNION FROM three)")
def pm_union(spark, sf_dir):
    return shown(pr.expanded(pr.pm_union(*_phase_models(spark, sf_dir)), -pr.FAR, 140), _x())


@query(_PHASES + _POINTS + "(FROM two EXCEPT FROM three)")
def pm_minus(spark, sf_dir):
    return shown(pr.expanded(pr.pm_minus(*_phase_models(spark, sf_dir)), -pr.FAR, 140), _x())


@query("SELECT 6::BIGINT AS length")
def pm_lcm(spark, sf_dir):
    right = pr.aligned(*_phase_models(spark, sf_dir))[1]
    return spark.range(1).select(F.lit(right.length).cast("long").alias("length"))


@query(_PHASES + "SELECT 2 * greatest(max(d) FILTER (c = 'view'), max(d) FILTER (c = 'click') + 10) + 1 AS first_cell FROM f")
def pm_align(spark, sf_dir):
    right = pr.aligned(*_phase_models(spark, sf_dir))[1]
    return spark.range(1).select(F.lit(right.lo).cast("long").alias("first_cell"))


# Motivating rule, weather and generated rules, and their updates.


def fault_sql(above70: str, facts: str = EV) -> str:
    part = lambda c: sql_coalesced(f"(SELECT u, 2 * t AS lo, 2 * (t + 86400) AS hi FROM ev WHERE c = '{c}')", "u")
    up = lambda src, c: f"(SELECT u, lo, hi + 172800 AS hi FROM {src} WHERE c = '{c}')"
    one, two = up("(SELECT u, c, 2 * t AS lo, 2 * t AS hi FROM ev WHERE value > 30)", "view"), up(above70, "click")
    meets = "greatest(a.lo, b.lo, p.lo, q.lo) <= least(a.hi, b.hi, p.hi, q.hi)"
    all4 = f"(SELECT a.u, greatest(a.lo, b.lo, p.lo, q.lo) AS lo, least(a.hi, b.hi, p.hi, q.hi) AS hi FROM {part('view')} a JOIN {part('click')} b ON a.u = b.u JOIN {sql_coalesced(one, 'u')} p ON p.u = a.u JOIN {sql_coalesced(two, 'u')} q ON q.u = a.u WHERE {meets})"
    return f"WITH {facts} " + sql_shown(sql_coalesced(all4, "u"), "u AS x")


_ABOVE70 = "(SELECT u, c, 2 * t AS lo, 2 * t AS hi FROM ev WHERE value > 70)"


def drawn_sql(pred: str, columns: str, source: str, k: str, seed: int = 1) -> str:
    """The draw of workloads.draw_update over coalesced rows (columns, lo, hi) of one predicate."""
    texts = [f"{c}::VARCHAR" for c in columns.split(", ")] + ["''"] * (3 - len(columns.split(", ")))
    return f"(SELECT {columns}, lo, hi FROM (SELECT *, row_number() OVER (ORDER BY md5(concat_ws('|', '{seed}', '{pred}', {', '.join(texts)}, lo::VARCHAR, hi::VARCHAR)), {', '.join(texts)}, lo) AS r, count(*) OVER () AS n FROM {source}) WHERE r <= {k})"


_A70 = sql_coalesced("(SELECT u, c, 2 * t AS lo, 2 * t AS hi FROM ev WHERE value > 70)", "u, c")
_FAULT_LEFT = sql_swept(_A70, drawn_sql("above70", "u, c", _A70, "100"), "minus", "u, c")


@query(fault_sql(_ABOVE70))
def rebuild_wfault(spark, sf_dir):
    return derived(wl.built(spark, sf_dir, "fault")[1], ("fault",), _x())


def _updated(spark, sf_dir, name: str, k=None, frac=None, insert=False, options=None, seed=1) -> tuple[wl.Workload, pr.PeriodicModel, mt.UpdateStats]:
    """The model after a draw is removed, or after it is put back into the model without it."""
    w, pm = wl.built(spark, sf_dir, name)
    drawn = wl.draws(spark, w, k, frac, seed)
    nothing = wl.mt.no_facts(spark)
    left, out, stats = mt.maintain(w.program, w.explicit, pm, drawn, nothing, options)
    if insert:
        _, out, stats = mt.maintain(w.program, left, out, nothing, drawn, options)
    return w, out, stats


@query(fault_sql(_FAULT_LEFT))
def maintain_wfault_del(spark, sf_dir):
    return derived(_updated(spark, sf_dir, "fault", 100)[1], ("fault",), _x())


@query(fault_sql(_ABOVE70))
def maintain_wfault_ins(spark, sf_dir):
    return derived(_updated(spark, sf_dir, "fault", 100, insert=True)[1], ("fault",), _x())


def meteo_left(k: str) -> str:
    left = sql_swept("hi", drawn_sql("reading_hi", "u", "hi", k), "minus", "u")
    return meteo_sql("rest", f"{_METEO_FACTS}, rest AS {left}")


@query(meteo_sql())
def rebuild_wmet(spark, sf_dir):
    return derived(wl.built(spark, sf_dir, "meteo")[1], METEO_HEADS)


@query(meteo_left("100"))
def maintain_wmet_del100(spark, sf_dir):
    return derived(_updated(spark, sf_dir, "meteo", 100)[1], METEO_HEADS)


@query(meteo_sql())
def maintain_wmet_ins100(spark, sf_dir):
    return derived(_updated(spark, sf_dir, "meteo", 100, insert=True)[1], METEO_HEADS)


@query(meteo_left("ceil(n * 0.1)"))
def maintain_wmet_del10pct(spark, sf_dir):
    return derived(_updated(spark, sf_dir, "meteo", frac=0.1)[1], METEO_HEADS)


@query(meteo_left("100"))
def maintain_wmet_later(spark, sf_dir):
    """Restored facts are only recognised in the second stage and spread in the third."""
    return derived(_updated(spark, sf_dir, "meteo", 100, options=mt.Options(propagate="later"))[1], METEO_HEADS)


@query(meteo_left("100"))
def maintain_wmet_body_change(spark, sf_dir):
    """Whole-body evaluation, which these rules allow in all stages."""
    return derived(_updated(spark, sf_dir, "meteo", 100, options=mt.Options(retract="body_change", grow="body_change"))[1], METEO_HEADS)


@query(meteo_sql())
def naive_rounds_wmet(spark, sf_dir):
    w = wl.built(spark, sf_dir, "meteo")[0]
    return derived(mt.rebuild(w.program, w.explicit, mt.Options(naive=True)), METEO_HEADS)


@query(meteo_left("100"))
def restore_wmet(spark, sf_dir):
    """What the first stage leaves and the second gives back."""
    w, pm = wl.built(spark, sf_dir, "meteo")
    drawn = wl.draws(spark, w, 100)
    span, o = bounds(w.explicit), mt.Options()
    gone = mt.retract(w.program, pm, drawn, span, o, mt.StageStats())
    rest = pr.pm_minus(pm, gone).kept()
    back = mt.restore(w.program, rest, gone, wl.without(w, drawn), span, o, mt.StageStats())
    return derived(pr.pm_union(rest, back), METEO_HEADS)


@query(f"WITH {_METEO_FACTS}, d AS {drawn_sql('reading_hi', 'u', 'hi', '100')} " + sql_shown(sql_coalesced("(SELECT 'hot' AS pred, u AS x, lo, hi FROM d)", "pred, x"), "pred, x"))
def affected_step(spark, sf_dir):
    w, pm = wl.built(spark, sf_dir, "meteo")
    return shown(Evaluator(w.program).affected(pm.core, wl.draws(spark, w, 100), {"reading_hi"}), "pred", F.col("a0").cast("long").alias("x"))


@query(f"WITH {_METEO_FACTS}, d AS {drawn_sql('reading_hi', 'u', 'hi', '100')} " + sql_shown(sql_coalesced("(SELECT 'hot' AS pred, u AS x, lo, hi FROM d)", "pred, x"), "pred, x"))
def body_change_affected(spark, sf_dir):
    w, pm = wl.built(spark, sf_dir, "meteo")
    return shown(Evaluator(w.program).affected(pm.core, wl.draws(spark, w, 100), {"reading_hi"}, "body_change"), "pred", F.col("a0").cast("long").alias("x"))


_TAPS = "tap AS (SELECT DISTINCT u, 2 * t AS lo, 2 * t AS hi FROM ev WHERE c = 'click')"
_LATE = "(SELECT u, lo, hi + 172800 AS hi FROM {})"
_COVERED = _LATE.format("rest")


@query(f"""WITH {EV}, {_TAPS}, gone AS {drawn_sql('tap', 'u', 'tap', '100')}, rest AS (SELECT * FROM tap EXCEPT SELECT * FROM gone),
 late AS {sql_coalesced(_LATE.format('gone'), 'u')}, lost AS {sql_swept('late', _COVERED, 'minus', 'u')}, held AS {sql_swept('late', _COVERED, 'intersect', 'u')}
 SELECT 'any_derivation' AS operator, (SELECT count(*) FROM gone) + (SELECT count(*) FROM late) AS retracted, (SELECT count(*) FROM held) AS restored
 UNION ALL SELECT 'body_change', (SELECT count(*) FROM gone) + (SELECT count(*) FROM lost), 0::BIGINT""")
def two_operators(spark, sf_dir):
    """The two affected-only operators apart: what a second witness (another click within a day) still gives is retracted
    and restored by the one that follows every derivation, and never touched by the one that tests the whole body."""
    program = parse_program("busy(u) :- PAST_SOME[0,86400] tap(u).")
    taps = wl.facts_at(wl.events(spark, sf_dir).filter("c = 'click'"), "tap", ["u"], F.col("t"))
    explicit = stored(iv.coalesced(taps, ATOM), "explicit")
    pm, drawn, rows = mt.rebuild(program, explicit), stored(wl.draw_update(explicit, 100), "draw"), []
    for operator in ("any_derivation", "body_change"):
        _, _, stats = mt.maintain(program, explicit, pm, drawn, wl.mt.no_facts(spark), mt.Options(retract=operator))
        rows.append((operator, stats.stages["retract"].facts, stats.stages["restore"].facts))
    return spark.createDataFrame(rows, "operator string, retracted long, restored long")


_SHIPS = sql_coalesced("(SELECT l_partkey AS p, 2 * date_diff('day', DATE '1970-01-01', l_shipdate::DATE)::BIGINT AS lo, 2 * (date_diff('day', DATE '1970-01-01', l_shipdate::DATE) + 5)::BIGINT AS hi FROM lineitem WHERE l_quantity > 25)", "p")


@query(f"WITH b AS {_SHIPS}, w AS (SELECT p, lo + 6 AS lo, hi FROM b WHERE lo + 6 <= hi), al AS {sql_coalesced('(SELECT p, lo, hi + 14 AS hi FROM w)', 'p')}, m AS (SELECT 'wave' AS pred, p AS x, lo, hi FROM w UNION ALL SELECT 'alert', p, lo, hi FROM al) " + sql_shown("m", "pred, x"))
def rebuild_wmet_twin(spark, sf_dir):
    return derived(wl.built(spark, sf_dir, "twin")[1], ("wave", "alert"))


# Highly recursive rules: days on which each predicate holds, in closed form up to day 150.


def generated_sql(removed: str = "", facts: str = "") -> str:
    first = "(SELECT u, c, min(floor((t - 1704067200) / 86400.0))::BIGINT AS d FROM ev GROUP BY u, c)"
    chain = lambda p, c, n: f"(SELECT u, unnest(generate_series(d, 150, {n}))::BIGINT AS d FROM {first} f WHERE c = '{c}'{removed.replace('PRED', p)})"
    six = f"(SELECT DISTINCT x.u, x.d FROM {chain('a0', 'view', 2)} x JOIN {chain('a1', 'click', 3)} y ON x.u = y.u AND x.d = y.d)"
    five = f"(SELECT u, d FROM {chain('a2', 'purchase', 5)} UNION SELECT u, unnest(generate_series(d, 150, 5))::BIGINT FROM {six} s)"
    rows = f"SELECT 'g3' AS pred, u, d FROM {chain('a0', 'view', 2)} UNION SELECT 'g4', u, d FROM {chain('a1', 'click', 3)} UNION SELECT 'g5', u, d FROM {five} z UNION SELECT 'g6', u, d FROM {six} s UNION SELECT 'g7', u, d FROM {six} s UNION SELECT 'g8', s.u, s.d FROM {six} s JOIN {five} z ON s.u = z.u AND s.d = z.d"
    cells_ = f"(SELECT pred, u AS x, 2 * d AS lo, 2 * d + 1 AS hi FROM ({rows}) WHERE d <= 119)"
    return f"WITH {EV}{facts} " + sql_shown(sql_coalesced(cells_, "pred, x"), "pred, x")


def _days(pm: pr.PeriodicModel) -> DataFrame:
    out = pr.expanded(pm, -20, 239).filter(F.col("pred").startswith("g"))
    return shown(out, "pred", _x())


@query(generated_sql())
def rebuild_wgen(spark, sf_dir):
    return _days(wl.built(spark, sf_dir, "generated")[1])


_GENERATED_FACTS = "(SELECT CASE c WHEN 'view' THEN 'a0' WHEN 'click' THEN 'a1' ELSE 'a2' END AS pred, u, min(floor((t - 1704067200) / 86400.0))::BIGINT AS d FROM ev WHERE c IN ('view', 'click', 'purchase') GROUP BY ALL)"


def generated_left(k: str, seed: int) -> str:
    """Without a draw from all explicit facts."""
    by = f"md5(concat_ws('|', '{seed}', pred, u::VARCHAR, '', '', (2 * d)::VARCHAR, (2 * d + 1)::VARCHAR)), pred, u::VARCHAR, d"
    drawn = f", g AS (SELECT pred, u FROM (SELECT *, row_number() OVER (ORDER BY {by}) AS r, count(*) OVER () AS n FROM {_GENERATED_FACTS}) WHERE r <= {k})"
    return generated_sql(" AND u NOT IN (SELECT u FROM g WHERE pred = 'PRED')", drawn)


for _k, _frac, _size, _seed in ((100, None, "100", 1), (None, 0.1, "10pct", 2)):

    def _gone(spark, sf_dir, k=_k, frac=_frac, seed=_seed):
        return _days(_updated(spark, sf_dir, "generated", k, frac, seed=seed)[1])

    def _put_back(spark, sf_dir, k=_k, frac=_frac, seed=_seed):
        return _days(_updated(spark, sf_dir, "generated", k, frac, insert=True, seed=seed)[1])

    query(generated_left("100" if _k else "ceil(n * 0.1)", _seed), f"maintain_wgen_del{_size}")(_gone)
    query(generated_sql(), f"maintain_wgen_ins{_size}")(_put_back)


# Conversations.

_TURNS = "k AS (SELECT DISTINCT conv_id AS x, turn, role FROM conversations), us AS (SELECT x, 2 * turn AS lo, 2 * turn + 1 AS hi FROM k WHERE role = 'user'), asst AS (SELECT x, 2 * turn AS lo, 2 * turn + 1 AS hi FROM k WHERE role = 'assistant')"
#: user_turn UNTIL[0,2] assistant_turn: the assistant turn itself, and a user stretch back from its first instant.
_ANSWERED = f"(SELECT x, lo, hi FROM asst UNION ALL SELECT a.x, greatest(a.lo - 4, h.lo) AS lo, least(h.hi + 1, a.hi) AS hi FROM {sql_coalesced('us', 'x')} h JOIN {sql_coalesced('asst', 'x')} a ON a.x = h.x AND a.lo <= h.hi + 1 AND h.lo <= a.hi)"


@query(f"WITH {_TURNS} " + sql_shown(sql_coalesced(_ANSWERED, "x"), "x"))
def until_wconv(spark, sf_dir):
    w = wl.talk(spark, sf_dir)
    return shown(Evaluator(w.program).applied(iv.coalesced(w.explicit, ATOM)).filter("pred = 'answered'"), _x())


# Mildly recursive rules: the plain joins and every temporal family.

_DAYNO = "date_diff('day', DATE '1970-01-01', {}::DATE)::BIGINT"
_ORD = f"ord AS (SELECT o_custkey AS c, o_orderkey AS o, 2 * {_DAYNO.format('o_orderdate')} AS lo, 2 * ({_DAYNO.format('o_orderdate')} + 30) AS hi FROM orders)"
_CON = f"con AS (SELECT DISTINCT l_orderkey AS o, l_partkey AS p, l_suppkey AS s, 2 * {_DAYNO.format('l_shipdate')} AS lo FROM lineitem)"


def trade_sql(ordered: str = "ord", facts: str = "") -> str:
    span = "sp AS (SELECT least((SELECT min(lo) FROM ord), (SELECT min(lo) FROM con)) AS lo, greatest((SELECT max(hi) FROM ord), (SELECT max(lo) FROM con)) AS hi)"
    bought = f"(SELECT c, s, con.lo, con.lo AS hi FROM {ordered} r JOIN con ON r.o = con.o AND con.lo BETWEEN r.lo AND r.hi)"
    clip = lambda cols, src: f"(SELECT {cols}, greatest(z.lo, sp.lo) AS lo, least(z.hi, sp.hi) AS hi FROM {src} z CROSS JOIN sp WHERE z.lo <= sp.hi AND z.hi >= sp.lo)"
    seg = "(SELECT c_custkey AS c, dense_rank() OVER (ORDER BY c_mktsegment) - 1 AS k FROM customer)"
    prio = "(SELECT o_orderkey AS o, dense_rank() OVER (ORDER BY o_orderpriority) - 1 AS k FROM orders)"
    typ = "(SELECT p_partkey AS p, dense_rank() OVER (ORDER BY p_type) - 1 AS k FROM part)"
    stat = "(SELECT o_orderkey AS o, dense_rank() OVER (ORDER BY o_orderstatus) - 1 AS k FROM orders)"
    imports = f"(SELECT c_nationkey AS x, s_nationkey AS y, b.lo, b.hi FROM {bought} b JOIN customer ON c_custkey = b.c JOIN supplier ON s_suppkey = b.s)"
    families = [
        f"SELECT 'bought_from' AS pred, c AS x, s AS y, lo, hi FROM {bought}",
        f"SELECT 'imports', x, y, lo, hi FROM {imports}",
        f"SELECT 'warm', x, y, lo, hi + 60 FROM {imports}",
        f"SELECT 'recent_' || k, c, -1, lo, hi FROM (SELECT z.c, k, z.lo, z.hi FROM {clip('c', f'(SELECT c, lo, hi + 60 AS hi FROM {ordered})')} z JOIN {seg} g ON g.c = z.c)",
        f"SELECT 'urgent_' || k, c, -1, lo, hi FROM (SELECT z.c, k, z.lo, z.hi FROM {clip('c, o', f'(SELECT c, o, lo, hi + 14 AS hi FROM {ordered})')} z JOIN {prio} g ON g.o = z.o)",
        f"SELECT 'moving_' || k, p, -1, lo, hi FROM (SELECT z.p, k, z.lo, z.hi FROM {clip('p', '(SELECT p, lo, lo + 28 AS hi FROM con)')} z JOIN {typ} g ON g.p = z.p)",
        f"SELECT 'pending_' || k, o, -1, lo, hi FROM (SELECT z.o, k, z.lo, z.hi FROM {clip('o', f'(SELECT o, lo, hi + 40 AS hi FROM {ordered})')} z JOIN {stat} g ON g.o = z.o)",
        # Zero is in the range, so an order's own time counts for every state.
        f"SELECT 'pending_' || k, o, -1, lo, hi FROM {ordered} CROSS JOIN (VALUES (0), (1), (2)) v(k)",
        f"SELECT 'active', c, -1, lo, hi + 120 FROM {ordered}",
        f"SELECT 'soon', c, -1, lo - 14, hi FROM {ordered}",
    ]
    return f"WITH {_ORD}, {_CON}, {span}{facts} " + sql_shown(sql_coalesced(f"({' UNION ALL '.join(families)})", "pred, x, y"), "pred, x, y")


TRADE_SHOWN = "bought_from imports warm active soon".split() + [f"{p}_{k}" for p, n in (("recent", 5), ("urgent", 5), ("moving", 6), ("pending", 3)) for k in range(n)]


def _traded(pm: pr.PeriodicModel) -> DataFrame:
    y = F.when(F.col("a1") == "", F.lit(-1).cast("long")).otherwise(F.expr("try_cast(a1 AS BIGINT)"))
    return derived(pm, tuple(TRADE_SHOWN), "pred", _x(), y.alias("y"))


@query(trade_sql())
def rebuild_wuni(spark, sf_dir):
    return _traded(wl.built(spark, sf_dir, "trade")[1])


def _orders_removed(w: wl.Workload, k: int | None = None, frac: float | None = None) -> DataFrame:
    return stored(wl.draw_update(w.explicit.filter("pred = 'ordered'"), k, frac), "draw")


def trade_left(k: str) -> str:
    return trade_sql("rest", f", rest AS {sql_swept('ord', drawn_sql('ordered', 'c, o', 'ord', k), 'minus', 'c, o')}")


@query(trade_left("100"))
def maintain_wuni_del100(spark, sf_dir):
    w, pm = wl.built(spark, sf_dir, "trade")
    return _traded(mt.maintain(w.program, w.explicit, pm, _orders_removed(w, 100), wl.mt.no_facts(spark))[1])


@query(trade_sql())
def maintain_wuni_ins100(spark, sf_dir):
    w, pm = wl.built(spark, sf_dir, "trade")
    drawn = _orders_removed(w, 100)
    less, out, _ = mt.maintain(w.program, w.explicit, pm, drawn, wl.mt.no_facts(spark))
    return _traded(mt.maintain(w.program, less, out, wl.mt.no_facts(spark), drawn)[1])


@query(trade_left("ceil(n * 0.1)"))
def maintain_wuni_del10pct(spark, sf_dir):
    w, pm = wl.built(spark, sf_dir, "trade")
    return _traded(mt.maintain(w.program, w.explicit, pm, _orders_removed(w, frac=0.1), wl.mt.no_facts(spark))[1])


@query()
def equal_wuni(spark, sf_dir):
    """Every head of the mildly recursive rules after a draw of 100 from all explicit facts is removed: facts of the
    rebuilt model, and what only the maintained or only the rebuilt model has (none)."""
    w, pm = wl.built(spark, sf_dir, "trade")
    target, out, _ = mt.maintain(w.program, w.explicit, pm, stored(wl.draw_update(w.explicit, 100), "draw"), wl.mt.no_facts(spark))
    out, fresh = out.kept("maintained"), mt.rebuild(w.program, stored(iv.coalesced(target, ATOM), "explicit"), maximal=True)
    count = lambda pm, name: pm.core.filter(F.col("pred").isin(*w.program.heads)).groupBy("pred").agg(F.count(F.lit(1)).alias(name))
    parts = count(fresh, "facts").join(count(pr.pm_minus(out, fresh), "only_maintained"), "pred", "full").join(count(pr.pm_minus(fresh, out), "only_rebuilt"), "pred", "full")
    return parts.fillna(0)


# Updates as such, checks and measures.


@query(f"WITH {_METEO_FACTS} SELECT u AS x, lo, hi FROM {drawn_sql('reading_hi', 'u', 'hi', '100')}")
def draw_update(spark, sf_dir):
    w = wl.built(spark, sf_dir, "meteo")[0]
    return wl.draws(spark, w, 100).select(_x(), "lo", "hi")


@query(f"WITH {VIEWS} " + sql_shown(f"(SELECT 'added' AS part, u, lo, hi FROM {sql_swept('b', 'a', 'minus', 'u')} UNION ALL SELECT 'removed', u, lo, hi FROM {sql_swept(sql_swept('(SELECT u, lo, hi - 86400 AS hi FROM a)', 'b', 'minus', 'u'), 'a', 'intersect', 'u')})", "part, u"))
def normalise_update(spark, sf_dir):
    a, b = user_views(spark, sf_dir)
    as_facts = lambda df: df.select(F.lit("p").alias("pred"), F.col("u").cast("string").alias("a0"), F.lit("").alias("a1"), F.lit("").alias("a2"), "lo", "hi")
    gone, new = mt.normalised(as_facts(a), as_facts(a.withColumn("hi", F.col("hi") - 86400)), as_facts(b))
    return union_all([shown(d, F.lit(p).alias("part"), F.col("a0").cast("long").alias("u")) for p, d in (("removed", gone), ("added", new))])


@query(meteo_sql("rest", f"{_METEO_FACTS}, rest AS {sql_swept(sql_swept('hi', drawn_sql('reading_hi', 'u', 'hi', '50', 2), 'minus', 'u'), '(SELECT u, lo, hi FROM hi WHERE false)', 'minus', 'u')}"))
def maintain_mixed(spark, sf_dir):
    """One update with removals and additions: from the facts without one draw to those without another."""
    w, pm = wl.built(spark, sf_dir, "meteo")
    one, two = wl.draws(spark, w, 50, seed=1), wl.draws(spark, w, 50, seed=2)
    start, model, _ = mt.maintain(w.program, w.explicit, pm, one, wl.mt.no_facts(spark))
    return derived(mt.maintain(w.program, start, model, two, stored(iv.sweep(one, two, "minus", ATOM), "draw"))[1], METEO_HEADS)


@query("SELECT 'only in maintained' AS side, 0::BIGINT AS n UNION ALL SELECT 'only in rebuilt', 0::BIGINT")
def pm_equal_check(spark, sf_dir):
    w, out, _ = _updated(spark, sf_dir, "fault", 100)
    fresh = mt.rebuild(w.program, wl.without(w, wl.draws(spark, w, 100)))
    count = lambda a, b, name: pr.pm_minus(a, b).core.agg(F.count(F.lit(1)).alias("n")).select(F.lit(name).alias("side"), "n")
    return count(out, fresh, "only in maintained").unionByName(count(fresh, out, "only in rebuilt"))


@query("SELECT 'example' AS workload, true AS saturated")
def saturation_check(spark, sf_dir):
    w, pm = wl.built(spark, sf_dir, "example")
    return spark.range(1).select(F.lit("example").alias("workload"), F.lit(mt.is_saturated(w.program, w.explicit, pm)).alias("saturated"))


@query(f"WITH {_METEO_FACTS} SELECT 2 * min(t) AS lo, 2 * (max(t) + 86400) AS hi FROM ev")
def time_bounds(spark, sf_dir):
    lo, hi = bounds(wl.built(spark, sf_dir, "meteo")[0].explicit)
    return spark.range(1).select(F.lit(lo).cast("long").alias("lo"), F.lit(hi).cast("long").alias("hi"))


@query("SELECT unnest(generate_series(-24, 34))::BIGINT AS point")
def ruler_points(spark, sf_dir):
    """Grid instants of the example between two ends: every multiple of the program's unit is one."""
    w = wl.example(spark, sf_dir)
    return spark.range(1).select(F.explode(F.sequence(F.lit(-24).cast("long"), F.lit(34).cast("long"), F.lit(1).cast("long"))).alias("point")).filter(F.col("point") % (1 / w.program.scale) == 0)


#: Explicit facts before coalescing.
_EXPLICIT = {
    "example": "(SELECT count(*) FROM supplier WHERE s_suppkey < (SELECT max(s_suppkey) FROM supplier))",
    "fault": "(SELECT count(*) FILTER (c = 'view') + count(*) FILTER (c = 'click') + count(*) FILTER (value > 30) + count(*) FILTER (value > 70) FROM ev)",
    "meteo": "(SELECT count(*) + count(*) FILTER (value > 100) FROM ev) + (SELECT count(*) FROM customer WHERE c_custkey IN (SELECT u FROM ev))",
    "generated": "(SELECT count(*) FROM (SELECT DISTINCT u, c FROM ev WHERE c IN ('view', 'click', 'purchase')))",
    "trade": "3 * (SELECT count(*) FROM orders) + (SELECT count(*) FROM lineitem) + 2 * (SELECT count(*) FROM customer) + (SELECT count(*) FROM part) + (SELECT count(*) FROM supplier) + (SELECT count(*) FROM nation)",
}
_RULES = {"example": "1, 0, 1, true", "fault": "1, 0, 1, false", "meteo": "2, 2, 4, false", "generated": "3, 8, 11, true", "trade": "29, 56, 85, true"}


@query(f"WITH {EV} SELECT * FROM (VALUES " + ", ".join(f"('{n}', {_RULES[n]}, ({_EXPLICIT[n]})::BIGINT)" for n in _RULES) + ") AS t(workload, temporal, plain, rules, recursive, facts)")
def dataset_stats(spark, sf_dir):
    loads = [wl.ALL[n](spark, sf_dir) for n in _RULES]
    rows = [(*wl.stats_row(w), w.explicit.count()) for w in loads]
    return spark.createDataFrame(rows, "workload string, temporal int, plain int, rules int, recursive boolean, facts long")


@query()
def recursiveness(spark, sf_dir):
    """Explicit facts, model facts (core) and their ratio for each workload that is built quickly."""
    rows = []
    for name in ("example", "fault", "meteo", "generated"):
        w, pm = wl.built(spark, sf_dir, name)
        e, m = w.explicit.count(), pm.core.count()
        rows.append((name, e, m, m / max(1, e)))
    return spark.createDataFrame(rows, "workload string, explicit long, model long, ratio double")


@query()
def stage_counts(spark, sf_dir):
    _, _, stats = _updated(spark, sf_dir, "meteo", 100)
    return spark.createDataFrame([(k, s.facts, s.raw, s.rounds) for k, s in stats.stages.items()], "stage string, facts long, raw long, rounds int")


@query()
def stage_breakdown(spark, sf_dir):
    _, _, stats = _updated(spark, sf_dir, "fault", 100)
    return spark.createDataFrame([(k, float(x)) for k, x in stats.shares().items()], "stage string, share double")


@query()
def rule_table(spark, sf_dir):
    """Rules of the trade workload, with the number of explicit facts (before coalescing) that a rule's body reads."""
    w = wl.trade(spark, sf_dir)
    explicit = {r["pred"]: r["count"] for r in w.explicit.groupBy("pred").count().collect()}  # one row a predicate
    rows = [(*row, sum(explicit.get(p, 0) for p in row[2].split(","))) for row in program_rows(w.program)]
    return spark.createDataFrame(rows, "rule int, head string, needs string, depth int, operators int, facts long")


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The worked example and the motivating rule, maintained."""
    return union_all([maintain_wex(spark, sf_dir).select(F.lit("r").alias("pred"), "*"), maintain_wfault_del(spark, sf_dir).select(F.lit("fault").alias("pred"), "*")])


def queries() -> dict[str, Query]:
    return _QUERIES | surface.queries()


def oracle_sql() -> dict[str, str]:
    return _SQL | surface.oracle_sql()


__all__ = ["Range", "flagship", "oracle_sql", "queries"]
