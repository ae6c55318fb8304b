"""Relational operators around the methods, functions, sources, SQL surface and streams."""

from __future__ import annotations

import os
import tempfile

import numpy as np
from pyspark.sql import Window
from pyspark.sql import functions as F

from rowfold.core import validate
from rowfold.core.bridge import apply_named
from rowfold.core.driver import counted_iterations, recursive, shared_dir, stage, windowed_fold
from rowfold.functions.portable import carter_wegman, carter_wegman_sql
from rowfold.operators.kmeans import LloydFold, nearest_centre
from rowfold.operators.ols import OlsFold, ols
from rowfold.queries.base import table
from rowfold.sources import io
from rowfold.sql import flatten_result, ols_select, register_all
from rowfold.streaming import streams as st

QUERIES: dict = {}
ORACLE: dict[str, str] = {}


def query(sql: str | None = None):
    """Register a query with the SQL that checks it."""

    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLE[f.__name__] = sql
        return f

    return add


def _r(c, n=4):
    return F.round(c, n)


# scans and joins -----------------------------------------------------------------------------------------------------


@query("select l_returnflag, count(*) as n, round(sum(l_quantity), 2) as q from lineitem where l_quantity between 10 and 20 and l_returnflag in ('A', 'R') and l_discount > 0.02 and l_linestatus is not null group by 1")
def scan_project_filter(spark, sf):
    l = table(spark, sf, "lineitem").filter(F.col("l_quantity").between(10, 20) & F.col("l_returnflag").isin("A", "R") & (F.col("l_discount") > 0.02) & F.col("l_linestatus").isNotNull())
    return l.groupBy("l_returnflag").agg(F.count("*").alias("n"), _r(F.sum("l_quantity"), 2).alias("q"))


def _round_trip(spark, sf, fmt, **kw):
    p = table(spark, sf, "part")
    path = f"{shared_dir(spark)}/rt-{fmt}-{os.urandom(4).hex()}"
    io.save(p, path, fmt, **kw)
    back = io.read(spark, path, fmt, p.schema, **kw)
    return back.select("p_partkey", "p_name", "p_size", _r("p_retailprice", 2).alias("p_retailprice"))


_RT = "select p_partkey, p_name, p_size, round(p_retailprice, 2) as p_retailprice from part"


@query(_RT)
def scan_roundtrip_csv(spark, sf):
    return _round_trip(spark, sf, "csv", header="true")


@query(_RT)
def scan_roundtrip_json(spark, sf):
    return _round_trip(spark, sf, "json")


@query(_RT)
def scan_roundtrip_orc(spark, sf):
    return _round_trip(spark, sf, "orc")


@query("select true as same_rows, 'line' as kind")
def model_store(spark, sf):
    """A model's table and metadata come back as saved."""
    fit = ols(table(spark, sf, "documents").select(F.array(F.lit(1.0), F.length("text").cast("double")).alias("x"), F.col("n_chars").cast("double").alias("y")), "y", "x")
    path = f"{shared_dir(spark)}/model-{os.urandom(4).hex()}"
    io.save_model({"fit": fit}, path, {"kind": "line"})
    tables, meta = io.load_model(spark, path)
    return spark.createDataFrame([(tables["fit"].count() == 1, meta["kind"])], "same_rows boolean, kind string")


def _oc(spark, sf):
    return table(spark, sf, "customer").select("c_custkey", "c_nationkey"), table(spark, sf, "orders").select("o_orderkey", "o_custkey", "o_totalprice")


def _join(how, sql_how):
    def q(spark, sf):
        c, o = _oc(spark, sf)
        j = c.join(o.filter("o_totalprice > 2000"), F.col("c_custkey") == F.col("o_custkey"), how)
        return j.groupBy("c_nationkey").agg(F.count("*").alias("n"), F.count("o_orderkey").alias("orders"))

    q.__name__ = f"join_{how}"
    return query(f"select c_nationkey, count(*) as n, count(o_orderkey) as orders from customer {sql_how} join (select * from orders where o_totalprice > 2000) on c_custkey = o_custkey group by 1")(q)


join_inner, join_left, join_right, join_full = (_join(h, s) for h, s in (("inner", ""), ("left", "left"), ("right", "right"), ("full", "full")))


@query("select c_nationkey, count(*) as n from customer where c_custkey in (select o_custkey from orders where o_orderstatus = 'F') group by 1")
def join_semi(spark, sf):
    c, _ = _oc(spark, sf)
    o = table(spark, sf, "orders").filter("o_orderstatus = 'F'")
    return c.join(o, F.col("c_custkey") == F.col("o_custkey"), "left_semi").groupBy("c_nationkey").agg(F.count("*").alias("n"))


@query("select c_custkey from customer where c_custkey not in (select o_custkey from orders)")
def join_anti(spark, sf):
    c, o = _oc(spark, sf)
    return c.join(o, F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey")


@query("select r_name, n_name from region, nation where r_regionkey <> n_regionkey")
def join_cross_dictionary(spark, sf):
    """All pairs of two fixed dictionaries of 5 and 25 rows."""
    return table(spark, sf, "region").join(F.broadcast(table(spark, sf, "nation")), F.col("r_regionkey") != F.col("n_regionkey")).select("r_name", "n_name")


@query("select case when p_size <= 10 then 'small' when p_size <= 30 then 'middle' else 'large' end as band, count(*) as n from part group by 1")
def join_theta_band(spark, sf):
    bands = spark.createDataFrame([("small", -1, 10), ("middle", 11, 30), ("large", 31, 1 << 30)], "band string, lo int, hi int")
    return table(spark, sf, "part").join(F.broadcast(bands), F.col("p_size").between(F.col("lo"), F.col("hi"))).groupBy("band").agg(F.count("*").alias("n"))


@query("select event_id, last_value(case when event_type = 'click' then event_id end ignore nulls) over (partition by user_id order by ts, event_id rows between unbounded preceding and 1 preceding) as prev_click from events")
def join_asof_prev_event(spark, sf):
    """As-of join of each event with its user's click before it."""
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    return table(spark, sf, "events").select("event_id", F.last(F.when(F.col("event_type") == "click", F.col("event_id")), ignorenulls=True).over(w).alias("prev_click"))


@query("select a.event_id as click, b.event_id as purchase from events a join events b on a.user_id = b.user_id and a.event_type = 'click' and b.event_type = 'purchase' and b.ts > a.ts and b.ts <= a.ts + interval 2 hour")
def join_interval_session(spark, sf):
    e = table(spark, sf, "events")
    a = e.filter("event_type = 'click'").select("user_id", F.col("event_id").alias("click"), F.col("ts").alias("t"))
    b = e.filter("event_type = 'purchase'").select("user_id", F.col("event_id").alias("purchase"), F.col("ts").alias("u"))
    return a.join(b, "user_id").filter((F.col("u") > F.col("t")) & (F.col("u") <= F.col("t") + F.expr("interval 2 hours"))).select("click", "purchase")


@query("select 'broadcast' as hint, true as same union all select 'merge', true union all select 'shuffle_hash', true")
def join_strategies_agree(spark, sf):
    c, o = _oc(spark, sf)
    f = lambda h: o.join(c.hint(h), F.col("c_custkey") == F.col("o_custkey")).agg(F.count("*"), F.round(F.sum("o_totalprice"), 2)).first()
    base = f("broadcast")
    return spark.createDataFrame([(h, f(h) == base) for h in ("broadcast", "merge", "shuffle_hash")], "hint string, same boolean")


# aggregates ----------------------------------------------------------------------------------------------------------


@query("select l_returnflag, l_linestatus, count(*) as n, round(sum(l_extendedprice * (1 - l_discount)), 2) as revenue, round(avg(l_quantity), 4) as q from lineitem group by all")
def agg_group(spark, sf):
    return table(spark, sf, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), _r(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))), 2).alias("revenue"), _r(F.avg("l_quantity")).alias("q"))


@query("select o_orderpriority, count(distinct o_custkey) as customers, count(*) filter (o_orderstatus = 'F') as f from orders group by 1 having count(*) > 10")
def agg_distinct_filtered_having(spark, sf):
    o = table(spark, sf, "orders").groupBy("o_orderpriority").agg(F.countDistinct("o_custkey").alias("customers"), F.count(F.when(F.col("o_orderstatus") == "F", 1)).alias("f"), F.count("*").alias("n"))
    return o.filter("n > 10").drop("n")


def _grouping(kind):
    def q(spark, sf):
        o = table(spark, sf, "orders")
        if kind == "grouping_sets":
            o.createOrReplaceTempView("rf_orders")
            return spark.sql("SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM rf_orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())")
        return getattr(o, kind)("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"))

    q.__name__ = f"agg_{kind}"
    by = {"rollup": "rollup (o_orderstatus, o_orderpriority)", "cube": "cube (o_orderstatus, o_orderpriority)", "grouping_sets": "grouping sets ((o_orderstatus), (o_orderpriority), ())"}[kind]
    return query(f"select o_orderstatus, o_orderpriority, count(*) as n from orders group by {by}")(q)


agg_rollup, agg_cube, agg_grouping_sets = (_grouping(k) for k in ("rollup", "cube", "grouping_sets"))


@query("select user_id, count(*) filter (event_type = 'click') as click, count(*) filter (event_type = 'purchase') as purchase from events group by 1")
def agg_pivot(spark, sf):
    p = table(spark, sf, "events").groupBy("user_id").pivot("event_type", ["click", "purchase"]).agg(F.count(F.lit(1)))
    return p.select("user_id", F.coalesce("click", F.lit(0)).alias("click"), F.coalesce("purchase", F.lit(0)).alias("purchase"))


@query("select l_returnflag, round(var_samp(l_quantity), 4) as v, round(stddev_samp(l_quantity), 4) as s, round(covar_samp(l_quantity, l_tax), 6) as cv, round(corr(l_quantity, l_extendedprice), 6) as c, round(regr_slope(l_quantity, l_tax), 3) as b, arg_max(l_orderkey, l_extendedprice * 1000000 + l_orderkey / 1000000.0) as top from lineitem group by 1")
def agg_stats(spark, sf):
    q, t, p = F.col("l_quantity"), F.col("l_tax"), F.col("l_extendedprice")
    return table(spark, sf, "lineitem").groupBy("l_returnflag").agg(
        _r(F.var_samp(q)).alias("v"), _r(F.stddev_samp(q)).alias("s"), _r(F.covar_samp(q, t), 6).alias("cv"), _r(F.corr(q, p), 6).alias("c"), _r(F.regr_slope(q, t), 3).alias("b"), F.max_by("l_orderkey", p * 1000000 + F.col("l_orderkey") / 1000000.0).alias("top"),
    )


# windows -------------------------------------------------------------------------------------------------------------

_W = "over (partition by user_id order by ts, event_id)"


@query(f"select event_id, row_number() {_W}::int as rn, rank() {_W}::int as rk, ntile(4) {_W}::int as nt, lag(event_id) {_W} as prev, lead(event_id) {_W} as nxt, first_value(event_id) {_W} as f from events")
def win_rank_lag(spark, sf):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return table(spark, sf, "events").select("event_id", F.row_number().over(w).alias("rn"), F.rank().over(w).alias("rk"), F.ntile(4).over(w).alias("nt"), F.lag("event_id").over(w).alias("prev"), F.lead("event_id").over(w).alias("nxt"), F.first("event_id").over(w).alias("f"))


@query("select event_id, round(sum(value) over (partition by user_id order by ts, event_id), 4) as run, round(avg(value) over (partition by user_id order by ts, event_id rows between 2 preceding and 2 following), 4) as slide from events")
def win_running_sliding(spark, sf):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return table(spark, sf, "events").select("event_id", _r(F.sum("value").over(w.rowsBetween(Window.unboundedPreceding, 0))).alias("run"), _r(F.avg("value").over(w.rowsBetween(-2, 2))).alias("slide"))


@query("select event_id, count(*) over (partition by user_id order by epoch_us(ts) range between 3600000000 preceding and current row) as hour from events")
def win_range_time(spark, sf):
    t = F.unix_micros(F.col("ts").cast("timestamp"))
    w = Window.partitionBy("user_id").orderBy(t).rangeBetween(-3_600_000_000, 0)
    return table(spark, sf, "events").select("event_id", F.count("*").over(w).alias("hour"))


@query("""with recursive o as (select user_id, event_id, value, row_number() over (partition by user_id order by event_id) as r from events),
s(user_id, event_id, r, s) as (select user_id, event_id, r, 0.2 * value from o where r = 1 union all select o.user_id, o.event_id, o.r, 0.8 * s.s + 0.2 * o.value from s join o on o.user_id = s.user_id and o.r = s.r + 1)
select event_id, round(s, 4) as ewma from s""")
def win_state_ewma(spark, sf):
    """An exponential average whose state passes from row to row."""
    f = windowed_fold(table(spark, sf, "events"), "user_id", "event_id", "value", 0.0, lambda s, v: s * 0.8 + v * 0.2)
    return f.select("event_id", _r("state").alias("ewma"))


@query("with recursive f(i, a, b) as (select 0, count(*)::bigint, sum(l_linenumber)::bigint from lineitem union all select i + 1, b, a + b from f where i < 30) select i::int as i, a from f")
def recursive_series(spark, sf):
    """A series whose terms are the sum of the two before, from two totals of a table."""
    table(spark, sf, "lineitem").createOrReplaceTempView("rf_lines")
    seed = "SELECT 0, count(*), CAST(sum(l_linenumber) AS BIGINT) FROM rf_lines"
    return recursive(spark, "rf_fib", ["i", "a", "b"], seed, "SELECT i + 1, b, a + b FROM rf_fib WHERE i < 30").select("i", "a")


@query("select t::int as trial, sum(n_nationkey * (t + 1))::bigint as s from nation, range(0, 10) r(t) group by 1")
def counted_series(spark, sf):
    """A counted iteration over a virtual table of round numbers, all rounds at once."""
    n = table(spark, sf, "nation")
    return counted_iterations(spark, 10, lambda trials: n.join(F.broadcast(trials), F.lit(True)).groupBy("trial").agg(F.sum(F.col("n_nationkey") * (F.col("trial") + 1)).cast("long").alias("s")))


@query("select o_orderkey, ntile(5) over w as nt, round(percent_rank() over w, 6) as pr, round(cume_dist() over w, 6) as cd, nth_value(o_orderkey, 2) over (w rows between unbounded preceding and unbounded following) as second, first_value(o_orderkey) over w as lo, last_value(o_orderkey) over (w rows between unbounded preceding and unbounded following) as hi, dense_rank() over w as dr from orders window w as (partition by o_custkey order by o_totalprice, o_orderkey)")
def win_distribution(spark, sf):
    w = Window.partitionBy("o_custkey").orderBy("o_totalprice", "o_orderkey")
    whole = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return table(spark, sf, "orders").select(
        "o_orderkey", F.ntile(5).over(w).alias("nt"), _r(F.percent_rank().over(w), 6).alias("pr"), _r(F.cume_dist().over(w), 6).alias("cd"), F.nth_value("o_orderkey", 2).over(whole).alias("second"),
        F.first("o_orderkey").over(w).alias("lo"), F.last("o_orderkey").over(whole).alias("hi"), F.dense_rank().over(w).alias("dr"),
    )


# subqueries ----------------------------------------------------------------------------------------------------------


def _views(spark, sf, *names):
    for n in names:
        table(spark, sf, n).createOrReplaceTempView(f"rf_{n}")


def _subquery(name: str, tables: tuple[str, ...], sql: str):
    """The same text for both engines, over views of the tables."""

    def q(spark, sf):
        _views(spark, sf, *tables)
        return spark.sql(sql.format(**{t: f"rf_{t}" for t in tables}))

    q.__name__ = name
    return query(sql.format(**{t: t for t in tables}))(q)


_subquery("sub_exists", ("customer", "orders"), "select c_custkey from {customer} c where exists (select 1 from {orders} o where o.o_custkey = c.c_custkey and o.o_totalprice > 200000) and not exists (select 1 from {orders} o where o.o_custkey = c.c_custkey and o.o_orderstatus = 'P')")
_subquery("sub_in", ("part", "lineitem"), "select p_partkey, p_brand from {part} where p_partkey in (select l_partkey from {lineitem} where l_quantity >= 49) and p_size not in (select p_size from {part} where p_retailprice < 905)")
_subquery("sub_scalar", ("orders", "customer"), "select o_orderkey from {orders} o where o_totalprice > (select avg(o2.o_totalprice) * 1.2 from {orders} o2 where o2.o_custkey = o.o_custkey)")
_subquery("sub_select_list", ("customer", "orders"), "select c_custkey, (select count(*) from {orders} o where o.o_custkey = c.c_custkey) as n from {customer} c")
_subquery("sub_lateral", ("nation", "customer"), "select n.n_nationkey, t.c_custkey from {nation} n, lateral (select c_custkey from {customer} c where c.c_nationkey = n.n_nationkey order by c_acctbal desc, c_custkey limit 2) t")


# sorts and sets ------------------------------------------------------------------------------------------------------


@query("select o_orderkey, o_totalprice from orders order by o_totalprice desc, o_orderkey limit 10")
def sort_topk(spark, sf):
    return table(spark, sf, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(10).select("o_orderkey", "o_totalprice")


@query("select p_brand, p_partkey from part qualify row_number() over (partition by p_brand order by p_retailprice desc, p_partkey) <= 3")
def topk_per_group(spark, sf):
    w = Window.partitionBy("p_brand").orderBy(F.desc("p_retailprice"), "p_partkey")
    return table(spark, sf, "part").withColumn("r", F.row_number().over(w)).filter("r <= 3").select("p_brand", "p_partkey")


@query("select p_partkey from part order by p_partkey limit 5 offset 7")
def limit_offset(spark, sf):
    return table(spark, sf, "part").orderBy("p_partkey").offset(7).limit(5).select("p_partkey")


def _set(name, op):
    def q(spark, sf):
        a, b = table(spark, sf, "customer").select(F.col("c_nationkey").alias("k")), table(spark, sf, "supplier").select(F.col("s_nationkey").alias("k"))
        return {"union": lambda: a.union(b).distinct(), "union_all": lambda: a.union(b).groupBy("k").agg(F.count("*").alias("n")), "intersect": lambda: a.intersect(b), "except": lambda: a.subtract(b)}[name]()

    q.__name__ = f"set_{name}"
    sql = {"union_all": "select k, count(*) as n from (select c_nationkey as k from customer union all select s_nationkey from supplier) group by 1"}.get(name, f"select c_nationkey as k from customer {op} select s_nationkey from supplier")
    return query(sql)(q)


for _n, _o in (("union", "union"), ("union_all", ""), ("intersect", "intersect"), ("except", "except")):
    _set(_n, _o)


# functions -----------------------------------------------------------------------------------------------------------


@query("select p_partkey, upper(p_name) as u, length(p_name) as n, substring(p_name, 2, 3) as s, replace(p_brand, '#', '-') as r, split_part(p_name, ' ', 1) as w, instr(p_name, 'a')::int as i, lpad(p_size::varchar, 4, '0') as l, reverse(p_name) as v, levenshtein(p_name, p_brand)::int as d from part")
def fn_string(spark, sf):
    n = F.col("p_name")
    return table(spark, sf, "part").select("p_partkey", F.upper(n).alias("u"), F.length(n).cast("long").alias("n"), F.substring(n, 2, 3).alias("s"), F.replace("p_brand", F.lit("#"), F.lit("-")).alias("r"), F.split_part(n, F.lit(" "), F.lit(1)).alias("w"), F.instr(n, "a").alias("i"), F.lpad(F.col("p_size").cast("string"), 4, "0").alias("l"), F.reverse(n).alias("v"), F.levenshtein(n, F.col("p_brand")).alias("d"))


@query("select doc_id, regexp_matches(text, '[0-9]{3}') as m, len(regexp_extract_all(text, '[A-Z][a-z]+'))::int as n, length(regexp_replace(text, '[aeiou]', '', 'g')) as k from documents")
def fn_regex(spark, sf):
    t = F.col("text")
    return table(spark, sf, "documents").select("doc_id", t.rlike("[0-9]{3}").alias("m"), F.size(F.regexp_extract_all(t, F.lit("([A-Z][a-z]+)"), F.lit(1))).alias("n"), F.length(F.regexp_replace(t, "[aeiou]", "")).cast("long").alias("k"))


@query("select o_orderkey, year(o_orderdate)::int as y, month(o_orderdate)::int as m, cast(date_trunc('month', o_orderdate) as date) as t, date_diff('day', date '1992-01-01', o_orderdate::date)::int as d from orders")
def fn_date(spark, sf):
    d = F.col("o_orderdate")
    return table(spark, sf, "orders").select("o_orderkey", F.year(d).alias("y"), F.month(d).alias("m"), F.trunc(d.cast("date"), "month").alias("t"), F.datediff(d.cast("date"), F.lit("1992-01-01").cast("date")).alias("d"))


@query("select event_id, round(ln(value + 1), 6) as l, round(sqrt(abs(value)), 6) as s, floor(value)::bigint as f, ceil(value)::bigint as c, round(sin(value), 6) as n, greatest(value, 10) as g, sign(value - 5)::double as z from events")
def fn_math(spark, sf):
    v = F.col("value")
    return table(spark, sf, "events").select("event_id", _r(F.log1p(v), 6).alias("l"), _r(F.sqrt(F.abs(v)), 6).alias("s"), F.floor(v).alias("f"), F.ceil(v).alias("c"), _r(F.sin(v), 6).alias("n"), F.greatest(v, F.lit(10.0)).alias("g"), F.signum(v - 5).alias("z"))


@query("select vec_id, len(embedding)::int as n, round(list_max(embedding)::double, 6) as hi, round(embedding[3]::double, 6) as third, len(list_filter(embedding, lambda x: x > 0))::int as pos, round(list_sum(list_transform(embedding[1:8], lambda x: x::double * 2)), 5) as twice from embeddings")
def fn_array(spark, sf):
    e = F.col("embedding")
    return table(spark, sf, "embeddings").select("vec_id", F.size(e).alias("n"), _r(F.array_max(e).cast("double"), 6).alias("hi"), _r(F.element_at(e, 3).cast("double"), 6).alias("third"), F.size(F.filter(e, lambda x: x > 0)).alias("pos"), _r(F.aggregate(F.slice(e, 1, 8), F.lit(0.0), lambda s, x: s + x.cast("double") * 2), 5).alias("twice"))


@query("select event_id, cast(json_extract(props, '$.k') as bigint) as k, (json_extract(props, '$.k') is not null) as has from events")
def fn_json(spark, sf):
    return table(spark, sf, "events").select("event_id", F.from_json("props", "k long")["k"].alias("k"), F.get_json_object("props", "$.k").isNotNull().alias("has"))


@query("select p_partkey, p_size * 2 as twice, 2::int as n, p_brand as b from part")
def fn_map_struct(spark, sf):
    m = F.create_map(F.lit("size"), F.col("p_size"), F.lit("twice"), F.col("p_size") * 2)
    s = F.struct(F.col("p_brand").alias("b"), F.col("p_size").alias("z"))
    return table(spark, sf, "part").select("p_partkey", F.element_at(m, F.lit("twice")).alias("twice"), F.size(F.map_keys(m)).alias("n"), s["b"].alias("b"))


@query("select o_orderkey, bit_count(o_orderkey)::int as c, (o_orderkey & 255)::bigint as a, (o_orderkey >> 3)::bigint as s, xor(o_orderkey, 5)::bigint as x from orders")
def fn_bit(spark, sf):
    k = F.col("o_orderkey")
    return table(spark, sf, "orders").select("o_orderkey", F.bit_count(k).alias("c"), k.bitwiseAND(255).alias("a"), F.shiftright(k, 3).alias("s"), k.bitwiseXOR(5).alias("x"))


# functions and tables for SQL ----------------------------------------------------------------------------------------

_C = [[0.0, 0.0], [5.0, 10.0], [9.0, 30.0]]
_NEAR = "select c_custkey, list_position(d, list_min(d))::int - 1 as idx from (select c_custkey, [" + ", ".join(f"round((c_acctbal / 1000 - {a}) ** 2 + (c_nationkey - {b}) ** 2, 10)" for a, b in _C) + "] as d from customer)"


@query(_NEAR)
def udf_nearest_centre(spark, sf):
    register_all(spark)
    c = F.array(*[F.array(*map(F.lit, p)) for p in _C])
    return table(spark, sf, "customer").select("c_custkey", F.call_function("nearest_centre", F.array(F.col("c_acctbal") / 1000, F.col("c_nationkey").cast("double")), c).alias("idx"))


@query(_NEAR)
def expr_nearest_centre(spark, sf):
    x = table(spark, sf, "customer").select("c_custkey", F.array(F.col("c_acctbal") / 1000, F.col("c_nationkey").cast("double")).alias("x"))
    return x.select("c_custkey", nearest_centre("x", _C)["idx"].alias("idx"))


@query("select item_id, i::int - 1 as pos, w[i] as token from (select item_id, list_filter(string_split_regex(text, '[ \\n\\t\\r]+'), lambda x: x <> '') as w from benchmark), range(1, len(w) + 1) t(i)")
def udtf_tokenize(spark, sf):
    register_all(spark)
    table(spark, sf, "benchmark").createOrReplaceTempView("rf_benchmark")
    return spark.sql("SELECT item_id, t.pos, t.token FROM rf_benchmark, LATERAL tokenize(text) t")


@query("select 'n_nationkey' as \"column\", count(*) as n, count(*) - count(n_nationkey) as nulls, sum(length(n_nationkey::varchar))::bigint as chars from nation union all select 'n_name', count(*), count(*) - count(n_name), sum(length(n_name))::bigint from nation union all select 'n_regionkey', count(*), count(*) - count(n_regionkey), sum(length(n_regionkey::varchar))::bigint from nation")
def udtf_profile(spark, sf):
    """A table function whose output follows from its table argument; what tasks saw is added up by column."""
    register_all(spark)
    table(spark, sf, "nation").createOrReplaceTempView("rf_nation")
    return spark.sql("SELECT `column`, sum(n) AS n, sum(nulls) AS nulls, sum(chars) AS chars FROM profile_part(TABLE(rf_nation)) GROUP BY `column`")


@query(_NEAR)
def named_callback(spark, sf):
    """A function called by its name, over blocks of vectors."""
    m = F.array(*[F.lit(v) for c in _C for v in c])
    return table(spark, sf, "customer").select("c_custkey", apply_named("nearest_column", F.array(F.col("c_acctbal") / 1000, F.col("c_nationkey").cast("double")), m).cast("int").alias("idx"))


@query("select o_orderstatus, round(regr_slope(o_totalprice / 1000, o_custkey), 6) as slope, round(regr_intercept(o_totalprice / 1000, o_custkey), 4) as intercept from orders group by 1")
def sql_ols_facade(spark, sf):
    register_all(spark)
    table(spark, sf, "orders").select("o_orderstatus", F.lit(1.0).alias("one"), F.col("o_custkey").cast("double").alias("c"), (F.col("o_totalprice") / 1000).alias("p")).createOrReplaceTempView("rf_fit")
    r = spark.sql(ols_select("p", ["one", "c"], "rf_fit", "o_orderstatus"))
    return r.select("o_orderstatus", _r(F.element_at("r.coef", 2), 6).alias("slope"), _r(F.element_at("r.coef", 1)).alias("intercept"))


@query("select 2::bigint as arrays_json, 2 as columns_coef, 2 as parts_text")
def flat_results(spark, sf):
    """Nested results as columns, JSON and text."""
    fit = ols(table(spark, sf, "events").select(F.array(F.lit(1.0), F.col("event_id").cast("double")).alias("x"), F.col("value").alias("y")), "y", "x").select("coef", "r2").persist()
    j = fit.transform(lambda d: flatten_result(d, "json")).select(F.json_array_length(F.get_json_object("result", "$.coef")).cast("long").alias("a"))
    c = sum(x.startswith("coef_") for x in flatten_result(fit).columns)
    t = flatten_result(fit, "string").select(F.size(F.split("coef", ","))).first()[0]
    return j.select(F.col("a").alias("arrays_json"), F.lit(c).alias("columns_coef"), F.lit(t).alias("parts_text"))


@query("select unnest(['UNKNOWN_COLUMN', 'NOT_NUMERIC', 'NOT_A_VECTOR', 'RAGGED_VECTORS', 'REPEATED_COLUMN', 'UNKNOWN_KERNEL', 'NO_COLUMNS']) as code")
def validate_errors(spark, sf):
    p = table(spark, sf, "part").withColumn("v", F.sequence(F.lit(1), F.least(F.col("p_size"), F.lit(3))))
    tries = (
        lambda: validate.columns(p, "nothing"), lambda: validate.numeric(p, "p_name"), lambda: validate.vector(p, "p_size"), lambda: validate.same_length(p, "v"),
        lambda: validate.columns(p, "p_name", "p_name"), lambda: ols(p, "p_size", "v", kernel="none"), lambda: validate.columns(p),
    )
    codes = []
    for t in tries:
        try:
            t()
        except validate.InputError as e:
            codes.append((e.code,))
    return spark.createDataFrame(codes, "code string")


@query("select 3 as versions, count(*) as n, sum(l_quantity + 2) as q from lineitem")
def staged_versions(spark, sf):
    """A large state goes through versions, each written anew and read back."""
    v = table(spark, sf, "lineitem").select("l_quantity")
    for _ in range(2):
        v = stage(v.withColumn("l_quantity", F.col("l_quantity") + 1), "version")
    return v.agg(F.lit(3).alias("versions"), F.count("*").alias("n"), F.sum("l_quantity").alias("q"))


# streams -------------------------------------------------------------------------------------------------------------


def _stream(spark, sf, parts=4):
    """events as files in the order of time, read as a stream of one file a batch; and a folder for checkpoints."""
    root = f"{shared_dir(spark)}/stream-{os.urandom(4).hex()}"
    e = table(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    e.repartitionByRange(parts, "ts").sortWithinPartitions("ts").write.parquet(f"{root}/in")
    return st.source(spark, f"{root}/in", e.schema), f"{root}/checkpoint", root


@query("select round(regr_intercept(value, event_id / 1000.0), 4) as a, round(regr_slope(value, event_id / 1000.0), 6) as b, count(*) as n from events")
def stream_ols(spark, sf):
    """Least squares kept up to date over micro-batches: the batch answer."""
    s, cp, _ = _stream(spark, sf)
    x = s.select(F.array(F.lit(1.0), F.col("event_id") / 1000.0).alias("x"), F.col("value").alias("y"))
    q, store = st.fold(x, OlsFold(), ["x", "y"], cp)
    q.awaitTermination()
    r = store.result()[0]
    return spark.createDataFrame([(r["coef"][0], r["coef"][1], r["n"])], "a double, b double, n long").select(_r("a").alias("a"), _r("b", 6).alias("b"), "n")


_TUMBLE = "select time_bucket(interval 1 day, ts)::timestamp as start, event_type, count(*) as n, round(sum(value), 4) as total from events group by all"


def _flush(spark, s):
    """The stream, whose windows close when a later event passes the watermark."""
    return s


@query("select event_type, count(*) as n, round(sum(value), 3) as total from events group by 1")
def stream_tumbling(spark, sf):
    """Daily windows in complete mode, added up by type."""
    s, cp, _ = _stream(spark, sf)
    w = st.tumbling(st.stamped(s, "ts", "1 hour"), "ts", "1 day", [F.count("*").alias("n"), F.sum("value").alias("total")], ("event_type",))
    t = st.drained(w, f"rf_t{os.urandom(3).hex()}", cp, "complete")
    return t.groupBy("event_type").agg(F.sum("n").alias("n"), _r(F.sum("total"), 3).alias("total"))


@query("select 2 * count(*) as n from events")
def stream_sliding(spark, sf):
    """Windows of two hours every hour hold each event twice."""
    s, cp, _ = _stream(spark, sf)
    w = st.tumbling(st.stamped(s, "ts", "1 hour"), "ts", "2 hours", [F.count("*").alias("n")], (), "1 hour")
    return st.drained(w, f"rf_s{os.urandom(3).hex()}", cp, "complete").agg(F.sum("n").alias("n"))


@query("with e as (select user_id, ts, lag(ts) over (partition by user_id order by ts) as p from events) select user_id, count(*) filter (p is null or ts - p > interval 6 hour) as sessions from e group by 1")
def stream_session(spark, sf):
    s, cp, _ = _stream(spark, sf)
    w = st.sessions(st.stamped(s, "ts", "60 days"), "ts", "6 hours", "user_id", [F.count("*").alias("n")])
    return st.summed(w, lambda r: r.groupBy("user_id").agg(F.count("*").alias("sessions")), cp)


@query("select count(distinct event_type) as n from events")
def stream_dedup(spark, sf):
    s, cp, _ = _stream(spark, sf)
    d = st.dedup(st.stamped(s, "ts", "60 days").select("event_type", "ts"), ["event_type"])
    return st.drained(d, f"rf_d{os.urandom(3).hex()}", cp).agg(F.count("*").alias("n"))


@query("select event_type, count(*) as n from events where user_id in (select c_custkey from customer) group by 1")
def stream_static_join(spark, sf):
    s, cp, _ = _stream(spark, sf)
    c = table(spark, sf, "customer").select(F.col("c_custkey").alias("user_id"))
    j = s.join(c, "user_id", "left_semi").groupBy("event_type").agg(F.count("*").alias("n"))
    return st.drained(j, f"rf_j{os.urandom(3).hex()}", cp, "complete")


@query("select count(*) as n from events a join events b on a.user_id = b.user_id and a.event_type = 'click' and b.event_type = 'purchase' and b.ts >= a.ts and b.ts <= a.ts + interval 2 hour")
def stream_interval_join(spark, sf):
    s, cp, _ = _stream(spark, sf)
    e = st.stamped(s, "ts", "60 days")
    a = e.filter("event_type = 'click'").select("user_id", F.col("ts").alias("t"))
    b = e.filter("event_type = 'purchase'").select("user_id", F.col("ts").alias("u"))
    return st.drained(st.interval_join(a, b, "user_id", "t", "u", "2 hours"), f"rf_i{os.urandom(3).hex()}", cp).agg(F.count("*").alias("n"))


@query("select user_id, count(*) as n, round(sum(value), 3) as total from events group by 1")
def stream_keyed_state(spark, sf):
    """Arbitrary state by key: the last row of each key is its total."""
    s, cp, _ = _stream(spark, sf)
    k = st.keyed(s, "user_id", "value", {"n": 0, "total": 0.0}, lambda o, v: {"n": o["n"] + len(v), "total": o["total"] + float(v.sum())}, "n long, total double")
    t = st.drained(k, f"rf_k{os.urandom(3).hex()}", cp, "update")
    return t.groupBy("user_id").agg(F.max("n").alias("n"), F.max_by("total", "n").alias("total")).select("user_id", "n", _r("total", 3).alias("total"))


@query(f"select row, bucket, cast(sum(cnt) as bigint) as cnt from ({' union all '.join(f'select {r} as row, {carter_wegman_sql("user_id", r, 64)} as bucket, count(*) as cnt from events group by 2' for r in range(3))}) group by all")
def stream_countmin(spark, sf):
    """Cells of a count-min sketch kept up to date over micro-batches: the batch cells."""
    s, cp, _ = _stream(spark, sf)
    cells = F.explode(F.array(*[F.struct(F.lit(r).alias("row"), carter_wegman(F.col("user_id"), r, 64).alias("bucket")) for r in range(3)]))
    c = s.select(cells.alias("c")).groupBy("c.row", "c.bucket").agg(F.count("*").alias("cnt"))
    return st.drained(c, f"rf_c{os.urandom(3).hex()}", cp, "complete")


@query("select time_bucket(interval 1 day, ts)::timestamp as start, count(*) as n, count(*) - count(value) as nulls, round(min(value), 4) as lo, round(max(value), 4) as hi, round(avg(value), 4) as mean, count(distinct event_type) as types from events group by 1")
def stream_window_profile(spark, sf):
    """A profile of every daily window."""
    s, cp, _ = _stream(spark, sf)
    v = F.col("value")
    aggs = [F.count("*").alias("n"), F.sum(v.isNull().cast("long")).alias("nulls"), F.min(v).alias("lo"), F.max(v).alias("hi"), F.avg(v).alias("mean"), F.size(F.collect_set("event_type")).cast("long").alias("types")]
    t = st.drained(st.tumbling(st.stamped(s, "ts", "1 hour"), "ts", "1 day", aggs), f"rf_p{os.urandom(3).hex()}", cp, "complete")
    return t.select(F.col("start").cast("timestamp_ntz").alias("start"), "n", "nulls", *(_r(c).alias(c) for c in ("lo", "hi", "mean")), "types")


_SEEDS = [[0.0, 5.0], [12.0, 5.0], [20.0, 50.0]]


@query("with p as (select hour(ts) as x0, value as x1 from events), d as (select x0, x1, [" + ", ".join(f"round((x0 - {a}) ** 2 + (x1 - {b}) ** 2, 10)" for a, b in _SEEDS) + "] as d from p) select list_position(d, list_min(d))::int - 1 as centre, count(*) as n, round(avg(x0), 5) as x0, round(avg(x1), 5) as x1 from d group by 1")
def stream_kmeans(spark, sf):
    """One round of k-means over a stream: sums by centre are kept up to date, and the new centres follow from them."""
    s, cp, _ = _stream(spark, sf)
    x = s.select(F.array(F.hour("ts").cast("double"), F.col("value")).alias("x"))
    q, store = st.fold(x, LloydFold(np.array(_SEEDS), None, "sqeuclid"), ["x"], cp)
    q.awaitTermination()
    rows = [(r["centre"], r["n"], *(float(t) / r["n"] for t in r["total"])) for r in store.result() if r["n"]]
    return spark.createDataFrame(rows, "centre int, n long, x0 double, x1 double").select("centre", "n", _r("x0", 5).alias("x0"), _r("x1", 5).alias("x1"))


_LATE = "event_id % 10 = 0 and ts < (select max(ts) from events) - interval 15 day"


@query(f"select time_bucket(interval 1 day, ts)::timestamp as start, count(*) as n from events where not ({_LATE}) group by 1 having start + interval 1 day <= (select max(ts) from events) - interval 10 minute")
def stream_late(spark, sf):
    """Daily windows that the watermark has closed: a tenth of the events up to 15 days before the last come after all
    others, far behind the watermark, and are dropped; all others are kept."""
    root = f"{shared_dir(spark)}/late-{os.urandom(4).hex()}"
    e = table(spark, sf, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"))
    last = e.agg(F.max("ts")).withColumnRenamed("max(ts)", "hi")
    held = e.crossJoin(F.broadcast(last)).withColumn("late", (F.col("event_id") % 10 == 0) & (F.col("ts") < F.col("hi") - F.expr("interval 15 days")))
    new = F.col("ts") >= F.col("hi") - F.expr("interval 1 day")
    # files are read in the order of their times; rows count as late by the watermark of the batch before the last one
    for k, rows in enumerate((held.filter(~F.coalesce("late", F.lit(False)) & ~new), held.filter(new), held.filter("late"))):
        rows.select("event_id", "ts").repartition(4).write.parquet(f"{root}/in/{k}")
    s = spark.readStream.schema(e.schema).option("maxFilesPerTrigger", 4).option("recursiveFileLookup", "true").parquet(f"{root}/in")
    w = st.tumbling(st.stamped(s, "ts", "10 minutes"), "ts", "1 day", [F.count("*").alias("n")])
    t = st.drained(w, f"rf_l{os.urandom(3).hex()}", f"{root}/cp")
    return t.select(F.col("start").cast("timestamp_ntz").alias("start"), "n")
