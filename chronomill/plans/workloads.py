"""Experiment workloads on the given tables: programs, explicit facts and update draws."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import ticks
from ..sources.store import ARGS, facts, facts_at, rigid, stored, table, union_all
from . import maintain as mt
from .periodic import PeriodicModel
from .rules import Program, parse_program

DAY = 86_400

EXAMPLE = "NEXT_ALL[9,10] r(x) :- PAST_ALL[0,1] r(x)."
FAULT = f"fault(u) :- has_a(u,c), has_b(u,d), PAST_SOME[0,{DAY}] above30(u,c), PAST_SOME[0,{DAY}] above70(u,d)."
METEO = f"""
hot(u) :- reading_hi(u).
zone_hot(n) :- hot(u), located(u,n).
wave(u) :- PAST_ALL[0,{DAY // 4}] hot(u).
NEXT_ALL[0,{DAY}] alert(u) :- wave(u).
"""
GENERATED = """
NEXT_ALL[2,2] g3(u) :- g3(u).  NEXT_ALL[3,3] g4(u) :- g4(u).  NEXT_ALL[5,5] g5(u) :- g5(u).
g3(u) :- a0(u).  g4(u) :- a1(u).  g5(u) :- a2(u).  g6(u) :- g3(u), g4(u).
g7(u) :- g6(u).  g6(u) :- g7(u).  g5(u) :- g6(u).  g8(u) :- g7(u), g5(u).
"""
TALK = """
answered(c) :- user_turn(c) UNTIL[0,2] assistant_turn(c).
following(c) :- assistant_turn(c) SINCE(0,2] user_turn(c).
echo(c) :- user_turn(c) SINCE[1,1] user_turn(c).
"""
#: Levels of the scale twin: parts with a large shipment as stations.
TWIN = """
busy(p) :- shipped(p).
wave(p) :- PAST_ALL[0,3] busy(p).
NEXT_ALL[0,7] alert(p) :- wave(p).
line_busy(s) :- busy(p), supplied(p,s).
"""


def trade_program(segments: int = 5, priorities: int = 5, types: int = 6, states: int = 3, nations: int = 25) -> str:
    """85 rules, 56 without and 29 with temporal operators, for the usual numbers of classes."""
    plain = [f"party(c) :- seg_{k}(c)." for k in range(segments)] + [f"in_region(c,r) :- cust_nat(c,{n}), nat_reg({n},r)." for n in range(nations)]
    plain += [f"order_any(o) :- prio_{k}(o)." for k in range(priorities)] + [f"product(p) :- type_{k}(p)." for k in range(types)] + [f"tracked(o) :- stat_{k}(o)." for k in range(states)]
    plain += """bought_from(c,s) :- ordered(c,o), contains(o,p,s).
imports(n,m) :- bought_from(c,s), cust_nat(c,n), supp_nat(s,m).
trades(n,m) :- imports(n,m).
trades(n,m) :- trades(m,n).
trades(n,m) :- trades(n,k), trades(k,m).
bloc(r,q) :- trades(n,m), nat_reg(n,r), nat_reg(m,q).
bloc(r,q) :- bloc(q,r).
domestic(n) :- imports(n,n).
party(c) :- bought_from(c,s).
supplying(s) :- bought_from(c,s).
bought_part(c,p) :- ordered(c,o), contains(o,p,s).
peer(s,t) :- bought_from(c,s), bought_from(c,t).""".split("\n")
    timed = [f"recent_{k}(c) :- PAST_SOME[0,30] ordered(c,o), seg_{k}(c)." for k in range(segments)] + [f"urgent_{k}(c) :- PAST_SOME[0,7] ordered(c,o), prio_{k}(o)." for k in range(priorities)]
    timed += [f"moving_{k}(p) :- PAST_SOME[0,14] contains(o,p,s), type_{k}(p)." for k in range(types)] + [f"pending_{k}(o) :- stat_{k}(o) SINCE[0,20] ordered(c,o)." for k in range(states)]
    timed += """active(c) :- PAST_SOME[0,60] ordered(c,o).
loyal(c) :- PAST_ALL[0,20] active(c).
NEXT_ALL[30,30] loyal(c) :- loyal(c), active(c).
NEXT_ALL[0,10] watch(s) :- supplying(s).
steady(s) :- PAST_ALL[0,5] watch(s).
NEXT_ALL[5,5] watch(s) :- steady(s), supplying(s).
warm(n,m) :- PAST_SOME[0,30] imports(n,m).
trades(n,m) :- PAST_ALL[0,10] warm(n,m).
soon(c) :- NEXT_SOME[0,7] ordered(c,o).
engaged(c) :- soon(c) UNTIL[0,7] active(c).""".split("\n")
    return "\n".join(plain + timed)


@dataclass
class Workload:
    name: str
    program: Program
    explicit: DataFrame
    #: Explicit predicates that updates are drawn from.
    changing: tuple[str, ...]


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """u, c, value, t (whole seconds)."""
    return table(spark, sf_dir, "events").select(F.col("user_id").alias("u"), F.col("event_type").alias("c"), "value", ticks.seconds(F.col("ts")).alias("t"), "props", "event_id")


def example(spark: SparkSession, sf_dir: str) -> Workload:
    keys = table(spark, sf_dir, "supplier").select("s_suppkey")
    last = keys.agg(F.max("s_suppkey")).first()[0]
    return Workload("example", parse_program(EXAMPLE), facts(keys.filter(F.col("s_suppkey") < last), "r", ["s_suppkey"], F.lit(0), F.lit(2)), ("r",))


def fault(spark: SparkSession, sf_dir: str) -> Workload:
    ev = events(spark, sf_dir)
    t = F.col("t")
    parts = [facts_at(ev.filter("c = 'view'"), "has_a", ["u", "c"], t, DAY), facts_at(ev.filter("c = 'click'"), "has_b", ["u", "c"], t, DAY), facts_at(ev.filter("value > 30"), "above30", ["u", "c"], t), facts_at(ev.filter("value > 70"), "above70", ["u", "c"], t)]
    return Workload("fault", parse_program(FAULT), union_all(parts), ("above70",))


def meteo(spark: SparkSession, sf_dir: str) -> Workload:
    ev = events(spark, sf_dir)
    first, last = ev.agg(F.min("t"), F.max("t")).first()
    users = ev.select("u").distinct()
    homes = table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("u"), F.col("c_nationkey").alias("n")).join(users, "u", "left_semi")
    parts = [facts_at(ev, "reading", ["event_id", "u"], F.col("t")), facts_at(ev.filter("value > 100"), "reading_hi", ["u"], F.col("t"), DAY // 2), rigid(homes, "located", ["u", "n"], first, last + DAY)]
    return Workload("meteo", parse_program(METEO), union_all(parts), ("reading_hi",))


def twin(spark: SparkSession, sf_dir: str) -> Workload:
    li = table(spark, sf_dir, "lineitem").select(F.col("l_partkey").alias("p"), F.col("l_suppkey").alias("s"), ticks.days(F.col("l_shipdate")).alias("d"), "l_quantity")
    first, last = li.agg(F.min("d"), F.max("d")).first()
    pairs = li.select("p", "s").distinct()
    parts = [facts_at(li.filter("l_quantity > 25"), "shipped", ["p"], F.col("d"), 5), rigid(pairs, "supplied", ["p", "s"], first, last + 10)]
    return Workload("twin", parse_program(TWIN), union_all(parts), ("shipped",))


def generated(spark: SparkSession, sf_dir: str) -> Workload:
    ev = events(spark, sf_dir)
    day = F.floor((F.col("t") - F.lit(1_704_067_200)) / DAY).cast("long")
    first = ev.select("u", "c", day.alias("d")).groupBy("u", "c").agg(F.min("d").alias("d"))
    parts = [facts_at(first.filter(F.col("c") == c), p, ["u"], F.col("d"), 1, end_open=True) for p, c in (("a0", "view"), ("a1", "click"), ("a2", "purchase"))]
    return Workload("generated", parse_program(GENERATED), union_all(parts), ("a0", "a1", "a2"))


def talk(spark: SparkSession, sf_dir: str) -> Workload:
    turns = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role")
    parts = [facts_at(turns.filter(F.col("role") == r), f"{r}_turn", ["conv_id"], F.col("turn"), 1, end_open=True) for r in ("user", "assistant")]
    return Workload("talk", parse_program(TALK), union_all(parts), ("user_turn",))


def ranked(df: DataFrame, column: str) -> DataFrame:
    """Values with their number in order, for predicates by class."""
    values = df.select(column).distinct()
    return values.withColumn("k", F.row_number().over(Window.orderBy(column)) - 1)  # a handful of classes


def trade(spark: SparkSession, sf_dir: str) -> Workload:
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderpriority", "o_orderstatus", ticks.days(F.col("o_orderdate")).alias("d"))
    li = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey", ticks.days(F.col("l_shipdate")).alias("d"))
    cust = table(spark, sf_dir, "customer").select("c_custkey", "c_nationkey", "c_mktsegment")
    supp = table(spark, sf_dir, "supplier").select("s_suppkey", "s_nationkey")
    part = table(spark, sf_dir, "part").select("p_partkey", "p_type")
    nation = table(spark, sf_dir, "nation").select("n_nationkey", "n_regionkey")
    spans = orders.agg(F.min("d").alias("a"), (F.max("d") + 30).alias("b")).unionAll(li.agg(F.min("d"), F.max("d"))).agg(F.min("a"), F.max("b")).first()
    parts = [facts_at(orders, "ordered", ["o_custkey", "o_orderkey"], F.col("d"), 30), facts_at(li, "contains", ["l_orderkey", "l_partkey", "l_suppkey"], F.col("d"))]
    for df, col, prefix, key in ((cust, "c_mktsegment", "seg", "c_custkey"), (orders, "o_orderpriority", "prio", "o_orderkey"), (part, "p_type", "type", "p_partkey"), (orders, "o_orderstatus", "stat", "o_orderkey")):
        named = df.select(key, col).join(F.broadcast(ranked(df, col)), col)  # one row a class
        parts.append(rigid(named, prefix, [key, "k"], *spans).select(F.concat("pred", F.lit("_"), "a1").alias("pred"), "a0", F.lit("").alias("a1"), "a2", "lo", "hi"))
    parts += [rigid(cust, "cust_nat", ["c_custkey", "c_nationkey"], *spans), rigid(supp, "supp_nat", ["s_suppkey", "s_nationkey"], *spans), rigid(nation, "nat_reg", ["n_nationkey", "n_regionkey"], *spans)]
    return Workload("trade", parse_program(trade_program()), union_all(parts), ("ordered", "contains"))


ALL = {"example": example, "fault": fault, "meteo": meteo, "generated": generated, "trade": trade, "talk": talk, "twin": twin}

_models: dict[tuple, tuple[Workload, PeriodicModel]] = {}


def built(spark: SparkSession, sf_dir: str, name: str) -> tuple[Workload, PeriodicModel]:
    """A workload with stored explicit facts and its model; kept for the session, as several queries update it."""
    key = (spark.sparkContext.applicationId, sf_dir, name)
    if key not in _models:
        w = ALL[name](spark, sf_dir)
        w.explicit = stored(mt.iv.coalesced(w.explicit, mt.ATOM), "explicit")
        _models[key] = (w, mt.rebuild(w.program, w.explicit, maximal=True))
    return _models[key]


def draw_update(explicit: DataFrame, k: int | None = None, frac: float | None = None, seed: int = 1) -> DataFrame:
    """A pseudo-random draw of k facts, or a share of them: first in the order of a hash of seed and fact."""
    if k is None:
        k = -int(-explicit.count() * frac // 1)
    return explicit.orderBy(F.md5(F.concat_ws("|", F.lit(str(seed)), *mt.ATOM, "lo", "hi")), *mt.ATOM, "lo").limit(k)


def pool(w: Workload) -> DataFrame:
    return w.explicit.filter(F.col("pred").isin(*w.changing))


def draws(spark: SparkSession, w: Workload, k: int | None = None, frac: float | None = None, seed: int = 1) -> DataFrame:
    return stored(draw_update(pool(w), k, frac, seed), "draw")


def without(w: Workload, removed: DataFrame) -> DataFrame:
    return stored(mt.iv.sweep(w.explicit, removed, "minus", mt.ATOM), "explicit")


def stats_row(w: Workload) -> tuple:
    p = w.program
    timed = p.temporal_rules()
    return w.name, timed, len(p.rules) - timed, len(p.rules), p.recursive()
