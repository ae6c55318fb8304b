"""Sketches, profiles, quantiles, arrays, sparse vectors and samples."""

from __future__ import annotations

from pyspark.sql import functions as F

from rowfold.functions import arrays as A
from rowfold.functions import sparse as S
from rowfold.functions.portable import carter_wegman_sql, mixed_sql, uniform_sql
from rowfold.operators import descriptive as D
from rowfold.operators import evaluate as E
from rowfold.operators.textops import terms
from rowfold.queries.base import table

W, DEPTH = 256, 4
TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def cm_cells(spark, sf):
    return D.countmin(table(spark, sf, "events"), "user_id", W, DEPTH)


def _cells_sql(src: str, v: str) -> str:
    return " union all ".join(f"select {r} as row, {carter_wegman_sql(v, r, W)} as bucket, count(*) as cnt from {src} where {v} is not null group by 2" for r in range(DEPTH))


def cm_point(spark, sf):
    src = table(spark, sf, "lineitem")
    cells = D.countmin(src, "l_partkey", W, DEPTH)
    return D.cm_point(cells, table(spark, sf, "part").select("p_partkey"), "p_partkey", W, DEPTH)


_POINT = f"with c as ({_cells_sql('lineitem', 'l_partkey')}), p as (select p_partkey, r.r as row, case r.r " + " ".join(f"when {r} then {carter_wegman_sql('p_partkey', r, W)}" for r in range(DEPTH)) + f" end as bucket from part, range(0, {DEPTH}) r(r)) select p_partkey, cast(min(coalesce(cnt, 0)) as bigint) as estimate from p left join c using (row, bucket) group by 1"


def cm_error(spark, sf):
    """How far a sketch's point estimates lie from the true counts."""
    true = table(spark, sf, "lineitem").groupBy(F.col("l_partkey").alias("p_partkey")).agg(F.count("*").alias("n"))
    return E.sketch_error(cm_point(spark, sf), true, "p_partkey").select("worst", F.round("mean", 6).alias("mean"), F.round("exact", 6).alias("exact"), "below")


_ERROR = f"with e as ({_POINT}), t as (select l_partkey as p_partkey, count(*) as n from lineitem group by 1), d as (select coalesce(estimate, 0) - n as d from t left join e using (p_partkey)) select max(abs(d)) as worst, round(avg(abs(d)), 6) as mean, round(avg((d = 0)::int), 6) as exact, count(*) filter (d < 0) as below from d"


def cm_bound(spark, sf):
    """Estimates never fall below the true counts, and lie within eps * N of them for at least 1 - delta of all values."""
    src = table(spark, sf, "lineitem")
    eps, delta = 0.01, 0.02
    w, d = D.cm_shape(eps, delta)
    true = src.groupBy("l_partkey").agg(F.count("*").alias("n"))
    e = D.cm_point(D.countmin(src, "l_partkey", w, d), true, "l_partkey", w, d).join(true, "l_partkey")
    n = src.count()
    return e.agg(F.min((F.col("estimate") >= F.col("n")).cast("int")).cast("boolean").alias("never_below"), (F.avg((F.col("estimate") <= F.col("n") + eps * n).cast("double")) >= 1 - delta).alias("within_bound"))


def cm_range(spark, sf):
    """Range counts from dyadic sketches are never below the exact ones, nor far above."""
    src = table(spark, sf, "events")
    ranges = [(1, 10), (5, 64), (0, 127), (33, 33)]
    levels = 8
    # a range adds up the error of every interval of its cover; the width keeps these together under the 10 rows allowed
    w, depth = D.cm_shape(10 / max(1, src.count() * max(len(D.dyadic_cover(a, b, levels)) for a, b in ranges)), 0.001)
    est = D.cm_range(D.cm_dyadic(src, "user_id", w, depth, levels), ranges, w, depth, levels)
    true = spark.createDataFrame(ranges, "low long, high long").join(src, (F.col("user_id") >= F.col("low")) & (F.col("user_id") <= F.col("high"))).groupBy("low", "high").agg(F.count("*").alias("n"))
    return est.join(true, ["low", "high"]).select("low", "high", "n", (F.col("estimate") >= F.col("n")).alias("never_below"), (F.col("estimate") <= F.col("n") * 1.1 + 10).alias("near"))


def cm_heavy(spark, sf):
    """Every event type and user above 0.8 per cent of events is reported."""
    src = table(spark, sf, "events")
    h = D.heavy_hitters(src, "user_id", 0.008, 1024, 5)
    true = src.groupBy(F.col("user_id").alias("value")).agg(F.count("*").alias("n")).filter(F.col("n") >= 0.008 * src.count())
    return true.join(h, "value", "left").select("value", "n", F.col("estimate").isNotNull().alias("found"))


def cm_dot_quantile(spark, sf):
    """The inner product of two sketches is no less than the true one; a dyadic quantile is near the true one."""
    e = table(spark, sf, "events")
    a, b = (D.countmin(e.filter(F.col("event_type") == k), "user_id", W, DEPTH) for k in ("click", "purchase"))
    n = lambda k: e.filter(F.col("event_type") == k).groupBy("user_id").agg(F.count("*").alias(k))
    true = n("click").join(n("purchase"), "user_id").agg(F.coalesce(F.sum(F.col("click") * F.col("purchase")), F.lit(0))).first()[0]
    dot = D.cm_dot(a, b).first()[0] or 0
    levels = 11
    q = D.cm_quantile(D.cm_dyadic(e, "user_id", 1024, 5, levels), 0.5, e.count(), 1024, 5, levels)
    lo, hi = e.agg(F.percentile("user_id", 0.45), F.percentile("user_id", 0.55)).first()
    return spark.createDataFrame([(dot >= true, lo <= q <= hi)], "dot_not_below boolean, quantile_near boolean")


def fm_bitmaps(spark, sf):
    return D.fm_bitmaps(table(spark, sf, "lineitem"), "l_partkey", 64)


_LOWBIT = "(case when {x} = 0 then 30 else bit_count((({x}) & -({x})) - 1) end)"
_FMROWS = f"select h % 64 as map, h // 64 as rest from (select {mixed_sql('l_partkey', '1')} as h from lineitem)"
FM_SQL = f"select map, bit_or(1::bigint << {_LOWBIT.format(x='rest')}) as bits from ({_FMROWS}) group by 1"


def fm_distinct(spark, sf):
    """The sketch's estimate lies within four standard errors, or small-range counting, of the exact number."""
    src = table(spark, sf, "lineitem")
    e = D.fm_distinct(src, "l_partkey").first()
    n = src.agg(F.countDistinct("l_partkey")).first()[0]
    return spark.createDataFrame([(n, abs(e["estimate"] - n) <= 4 * e["std_error"] * n)], "exact long, near boolean")


def distinct_methods(spark, sf):
    src = table(spark, sf, "orders")
    n = D.distinct_count(src, "o_custkey").first()[0]
    rows = [(m, abs(D.distinct_count(src, "o_custkey", m).first()[0] - n) <= lim * n) for m, lim in (("exact", 0), ("hll", 0.1), ("approx", 0.2), ("theta", 0.1), ("fm", 0.4))]
    return spark.createDataFrame(rows, "method string, near boolean")


def _profile(name):
    def q(spark, sf):
        df = table(spark, sf, name)
        return D.profile(df, "exact", quartiles=False).select("pos", "column", "rows", "nulls", "distinct", F.round("mean", 3).alias("mean"))

    q.__name__ = f"profile_{name}"
    q.__doc__ = f"Rows, nulls, distinct values and mean value or length of every column of {name}."
    return q


_COLUMNS = {
    "region": "r_regionkey r_name", "nation": "n_nationkey n_name n_regionkey", "customer": "c_custkey c_name c_nationkey c_acctbal c_mktsegment", "supplier": "s_suppkey s_name s_nationkey s_acctbal",
    "part": "p_partkey p_name p_brand p_type p_size p_retailprice", "orders": "o_orderkey o_custkey o_orderstatus o_totalprice o_orderdate o_orderpriority",
    "lineitem": "l_orderkey l_partkey l_suppkey l_linenumber l_quantity l_extendedprice l_discount l_tax l_returnflag l_linestatus l_shipdate", "events": "event_id ts user_id event_type value props",
    "documents": "doc_id text lang source n_chars", "embeddings": "vec_id embedding label", "pages": "page_id url html", "benchmark": "item_id text", "labels": "doc_id quality toxic", "conversations": "conv_id turn role text",
}
_TEXTS = set("r_name n_name c_name c_mktsegment s_name p_name p_brand p_type o_orderstatus o_orderpriority l_returnflag l_linestatus event_type props text lang source url html role".split())


def _profile_sql(name: str) -> str:
    out = []
    for i, c in enumerate(_COLUMNS[name].split()):
        mean = f"avg(length({c}))" if c in _TEXTS else f"avg(len({c}))" if c == "embedding" else "null::double" if c in ("ts", "o_orderdate", "l_shipdate") else f"avg({c}::double)"
        out.append(f"select {i} as pos, '{c}' as \"column\", count(*) as rows, count(*) - count({c}) as nulls, count(distinct {c}) as \"distinct\", round({mean}, 3) as mean from {name}")
    return " union all ".join(out)


def profile_shape(spark, sf):
    """Least and greatest values as text, spread and quartiles are filled for numbers."""
    p = D.profile(table(spark, sf, "orders")).filter("column = 'o_totalprice'")
    return p.select((F.col("q25") <= F.col("q50")).alias("a"), (F.col("q50") <= F.col("q75")).alias("b"), (F.col("std") > 0).alias("c"), F.col("min").isNotNull().alias("d"))


def top_types(spark, sf):
    return D.top_values(table(spark, sf, "events"), "event_type", 3)


def quantiles_exact(spark, sf):
    return D.quantile(table(spark, sf, "events"), "value", [0.1, 0.5, 0.9], "exact", ["event_type"]).select("event_type", "q", F.round("value", 6).alias("value"))


def quantiles_discrete(spark, sf):
    return D.quantile(table(spark, sf, "orders"), "o_totalprice", [0.25, 0.5, 0.99], "discrete")


def quantiles_bisect(spark, sf):
    return D.quantile(table(spark, sf, "orders"), "o_totalprice", [0.25, 0.5, 0.99], "bisect")


def quantile_approx_err(spark, sf):
    """Rank errors of the approximate methods stay within 2 per cent."""
    src = table(spark, sf, "events")
    n = src.count()
    rows = []
    for m in ("approx", "kll"):
        for r in D.quantile(src, "value", [0.1, 0.5, 0.9], m).collect():
            rank = src.filter(F.col("value") <= r["value"]).count() / n
            rows.append((m, r["q"], abs(rank - r["q"]) <= 0.02))
    return spark.createDataFrame(rows, "method string, q double, near boolean")


def _pair(spark, sf):
    e = table(spark, sf, "embeddings").select("vec_id", F.slice(F.col("embedding").cast("array<double>"), 1, 6).alias("x"))
    return e.withColumn("y", F.transform(F.reverse("x"), lambda v: v + 1))


def array_ops(spark, sf):
    r = lambda c: F.round(c, 6)
    return _pair(spark, sf).select(
        "vec_id", r(A.total("x")).alias("total"), r(A.dot("x", "y")).alias("dot"), r(A.sum_abs("x")).alias("sum_abs"), r(A.mean("x")).alias("mean"), r(A.std("x")).alias("std"), r(A.minimum("x")).alias("lo"),
        r(A.maximum("x")).alias("hi"), A.argmax("x").alias("at"), r(A.norm2("x")).alias("norm2"), r(A.total(A.mult("x", "y"))).alias("mult"), r(A.euclid("x", "y")).alias("euclid"),
    )


ARRAY_SQL = """
with e as (select vec_id, list_transform(embedding[1:6], lambda v: v::double) as x from embeddings), p as (select vec_id, x, list_transform(list_reverse(x), lambda v: v + 1) as y from e)
select vec_id, round(list_sum(x), 6) as total, round(list_inner_product(x, y), 6) as dot, round(list_sum(list_transform(x, lambda v: abs(v))), 6) as sum_abs, round(list_avg(x), 6) as mean, round(list_stddev_samp(x), 6) as std,
round(list_min(x), 6) as lo, round(list_max(x), 6) as hi, cast(list_position(x, list_max(x)) - 1 as bigint) as at, round(sqrt(list_inner_product(x, x)), 6) as norm2, round(list_inner_product(x, y), 6) as mult, round(list_distance(x, y), 6) as euclid from p"""


def array_aggregates(spark, sf):
    e = table(spark, sf, "embeddings").select("label", F.slice(F.col("embedding").cast("array<double>"), 1, 3).alias("x"))
    out = A.aggregate_arrays(e, "x", ("label",), "avg").withColumnRenamed("values", "avg").join(A.aggregate_arrays(e, "x", ("label",), "max").withColumnRenamed("values", "max"), "label")
    return out.select("label", F.posexplode(F.arrays_zip("avg", "max")).alias("pos", "z")).select("label", "pos", F.round("z.avg", 6).alias("avg"), F.round("z.max", 6).alias("max"))


def _runs(spark, sf):
    """Vectors of part sizes, cut to few values, of each brand's parts."""
    p = table(spark, sf, "part").withColumn("r", F.expr("row_number() over (partition by p_brand order by p_partkey)"))
    g = p.groupBy("p_brand").agg(F.transform(F.array_sort(F.collect_list(F.struct("r", (F.floor(F.col("p_size") / 20)).cast("double").alias("v")))), lambda s: s["v"]).alias("x"))
    return g.withColumn("s", S.from_dense("x")).withColumn("t", S.from_dense(F.reverse("x")))


def sparse_ops(spark, sf):
    d = S.dot(S.distance(_runs(spark, sf), "s", "t", "dist"), "s", "t", "dot")
    return d.select("p_brand", S.length("s").alias("n"), S.norm1("s").alias("norm1"), F.round(S.norm2("s"), 6).alias("norm2"), "dot", F.round("dist", 6).alias("dist"), S.lookup("s", 2).alias("third"), (S.to_dense("s") == F.col("x")).alias("round_trip"), A.total(S.to_dense(S.apply("s", lambda v: v * 2))).alias("doubled"))


SPARSE_SQL = """
with p as (select *, row_number() over (partition by p_brand order by p_partkey) as r from part), g as (select p_brand, list(floor(p_size / 20)::double order by r) as x from p group by 1)
select p_brand, len(x)::bigint as n, list_sum(list_transform(x, lambda v: abs(v))) as norm1, round(sqrt(list_inner_product(x, x)), 6) as norm2, list_inner_product(x, list_reverse(x)) as dot, round(list_distance(x, list_reverse(x)), 6) as dist, x[3] as third, true as round_trip, 2 * list_sum(x) as doubled from g"""


def sparse_sum(spark, sf):
    return S.sum_vectors(_runs(spark, sf), "s").select("pos", "sum", "n_nonzero")


SPARSE_SUM_SQL = "with p as (select *, row_number() over (partition by p_brand order by p_partkey) as r from part) select r - 1 as pos, sum(floor(p_size / 20)::double) as sum, count(*) as n_nonzero from p where floor(p_size / 20) <> 0 group by 1"


def tfidf(spark, sf):
    t = terms(table(spark, sf, "benchmark"), "item_id", "text")
    return S.tf_idf(t).select("doc_id", "term", F.round("tf_idf", 6).alias("tf_idf"))


TFIDF_SQL = "with t as (select item_id as doc_id, unnest(regexp_extract_all(lower(text), '[a-z]+')) as term from benchmark), c as (select doc_id, term, count(*) as cnt from t group by all), n as (select count(distinct doc_id)::double as n from t) select doc_id, term, round(cnt * ln(n / count(*) over (partition by term)), 6) as tf_idf from c, n"


def sample_bernoulli_hash(spark, sf):
    return D.sample_rows(table(spark, sf, "orders"), "o_orderkey", 0.1, 7).select("o_orderkey")


def sample_stratified(spark, sf):
    return D.stratified(table(spark, sf, "orders"), "o_orderkey", "o_orderstatus", {"F": 0.05, "O": 0.2}, 7).select("o_orderkey", "o_orderstatus")


def sample_vs_full_tail(spark, sf):
    """Customers with few lines: how many a 10 per cent sample of the lines loses altogether."""
    l = table(spark, sf, "lineitem").join(table(spark, sf, "orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey"), "l_orderkey")
    full = l.groupBy("o_custkey").agg(F.count("*").alias("n"))
    kept = D.sample_rows(l, "l_orderkey", 0.1, 11).select("o_custkey").distinct().withColumn("kept", F.lit(1))
    band = F.when(F.col("n") < 20, "few").when(F.col("n") < 60, "some").otherwise("many")
    return full.join(kept, "o_custkey", "left").groupBy(band.alias("band")).agg(F.count("*").alias("groups"), F.count(F.when(F.col("kept").isNull(), 1)).alias("lost"))


TAIL_SQL = f"""
with l as (select l_orderkey, o_custkey from lineitem join orders on o_orderkey = l_orderkey), f as (select o_custkey, count(*) as n from l group by 1), k as (select distinct o_custkey from l where {uniform_sql('l_orderkey', '11')} < 0.1)
select case when n < 20 then 'few' when n < 60 then 'some' else 'many' end as band, count(*) as groups, count(*) filter (k.o_custkey is null) as lost from f left join k using (o_custkey) group by 1"""


_PROFILES = [_profile(n) for n in TABLES]
QUERIES = {f.__name__: f for f in (
    cm_cells, cm_point, cm_error, cm_bound, cm_range, cm_heavy, cm_dot_quantile, fm_bitmaps, fm_distinct, distinct_methods, *_PROFILES, profile_shape, top_types, quantiles_exact, quantiles_discrete, quantiles_bisect,
    quantile_approx_err, array_ops, array_aggregates, sparse_ops, sparse_sum, tfidf, sample_bernoulli_hash, sample_stratified, sample_vs_full_tail,
)}
_DISC = "select unnest([0.25, 0.5, 0.99])::double as q, unnest(quantile_disc(o_totalprice, [0.25, 0.5, 0.99])) as value from orders"
ORACLE = {
    "cm_cells": _cells_sql("events", "user_id"), "cm_point": _POINT, "cm_error": _ERROR, "cm_bound": "select true as never_below, true as within_bound",
    "cm_range": "select low, high, count(*) as n, true as never_below, true as near from (values (1::bigint, 10::bigint), (5, 64), (0, 127), (33, 33)) r(low, high) join events on user_id between low and high group by all",
    "cm_heavy": "select user_id as value, count(*) as n, true as found from events group by 1 having count(*) >= 0.008 * (select count(*) from events)",
    "cm_dot_quantile": "select true as dot_not_below, true as quantile_near", "fm_bitmaps": FM_SQL,
    "fm_distinct": "select count(distinct l_partkey) as exact, true as near from lineitem",
    "distinct_methods": "select unnest(['exact', 'hll', 'approx', 'theta', 'fm']) as method, true as near",
    **{f"profile_{n}": _profile_sql(n) for n in TABLES},
    "profile_shape": "select true as a, true as b, true as c, true as d",
    "top_types": "select event_type as value, count(*) as n from events group by 1 order by n desc, value limit 3",
    "quantiles_exact": " union all ".join(f"select event_type, {q}::double as q, round(quantile_cont(value, {q}), 6) as value from events group by 1" for q in (0.1, 0.5, 0.9)),
    "quantiles_discrete": _DISC, "quantiles_bisect": _DISC,
    "quantile_approx_err": "select method, q, true as near from (select unnest(['approx', 'kll']) as method), (select unnest([0.1, 0.5, 0.9])::double as q)",
    "array_ops": ARRAY_SQL,
    "array_aggregates": "select label, i::int - 1 as pos, round(avg(embedding[i]::double), 6) as avg, round(max(embedding[i]::double), 6) as max from embeddings, range(1, 4) t(i) group by label, i",
    "sparse_ops": SPARSE_SQL, "sparse_sum": SPARSE_SUM_SQL, "tfidf": TFIDF_SQL,
    "sample_bernoulli_hash": f"select o_orderkey from orders where {uniform_sql('o_orderkey', '7')} < 0.1",
    "sample_stratified": f"select o_orderkey, o_orderstatus from orders where {uniform_sql('o_orderkey', '7')} < case o_orderstatus when 'F' then 0.05 when 'O' then 0.2 else 0 end",
    "sample_vs_full_tail": TAIL_SQL,
}
