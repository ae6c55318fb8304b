"""Least squares, logistic regression, convex solvers and linear systems."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rowfold.core.driver import iterate
from rowfold.core.fold import run_fold
from rowfold.functions import features
from rowfold.functions.portable import M, uniform, uniform_sql
from rowfold.operators import convex
from rowfold.operators import evaluate as E
from rowfold.operators.descriptive import bootstrap, bootstrap_summary, cg_solve, triple_matvec
from rowfold.operators.logistic import LogisticFold, logistic, logistic_grouped, logistic_many, predict_logistic
from rowfold.operators.ols import OlsFold, ols, ols_sparse, predict_ols, simple_ols
from rowfold.operators.supervised import random_features, svm
from rowfold.operators.unsupervised import row_sum
from rowfold.queries.base import NOISY_SQL, TOXIC_SQL, WORDS_SQL, newton_sql, ols_sql, sums_sql, table, toxic, words

# fixtures ------------------------------------------------------------------------------------------------------------


def line(spark: SparkSession, sf: str) -> DataFrame:
    c = lambda n: F.col(n).cast("double")
    return table(spark, sf, "lineitem").select("l_partkey", "l_orderkey", F.array(F.lit(1.0), c("l_quantity"), c("l_discount"), c("l_tax")).alias("x"), (c("l_extendedprice") / 1000).alias("y"))


LINE_SQL = "select l_partkey, l_orderkey, 1.0::double as x0, l_quantity::double as x1, l_discount::double as x2, l_tax::double as x3, l_extendedprice / 1000 as y from lineitem"


def doc(spark: SparkSession, sf: str) -> DataFrame:
    return table(spark, sf, "documents").select("doc_id", F.array(F.lit(1.0), words("text") / 100).alias("x"), (F.col("n_chars") / 100).alias("y"))


DOC_SQL = f"select doc_id, 1.0::double as x0, {WORDS_SQL} / 100 as x1, n_chars / 100.0::double as y from documents"


def event(spark: SparkSession, sf: str) -> DataFrame:
    sec = F.unix_micros(F.col("ts").cast("timestamp")) / 1e6 - 1704067200
    return table(spark, sf, "events").select(F.array(F.lit(1.0), F.col("event_id") / 1000.0).alias("x"), (sec / 1000).alias("y"))


EVENT_SQL = "select 1.0::double as x0, event_id / 1000.0::double as x1, (epoch_us(ts) / 1000000.0::double - 1704067200) / 1000 as y from events"


def told(fit: DataFrame, by: tuple[str, ...] = (), digits: int = 4) -> DataFrame:
    """pos, coef, std_err, t_stat, r2, n: a composite result as rows."""
    z = F.posexplode(F.arrays_zip("coef", "std_err", "t_stats")).alias("pos", "z")
    return fit.select(*by, "r2", "n", z).select(*by, "pos", F.round("z.coef", digits).alias("coef"), F.round("z.std_err", digits).alias("std_err"), F.round("z.t_stats", 3).alias("t_stat"), F.round("r2", 6).alias("r2"), "n")


# least squares -------------------------------------------------------------------------------------------------------


def ols_doclen(spark, sf):
    return told(ols(doc(spark, sf), "y", "x"))


def ols_event_time(spark, sf):
    return told(ols(event(spark, sf), "y", "x"))


def ols_price(spark, sf):
    return told(ols(line(spark, sf), "y", "x"))


def ols_price_expr(spark, sf):
    return told(ols(line(spark, sf), "y", "x", kernel="expr", d=4))


def ols_price_block(spark, sf):
    return told(ols(line(spark, sf), "y", "x", kernel="block", block=2))


def ols_price_serial(spark, sf):
    return told(ols(line(spark, sf), "y", "x", mode="serial"))


def ols_price_jvm(spark, sf):
    return told(ols(line(spark, sf), "y", "x", kernel="jvm"))


def ols_price_sparse(spark, sf):
    src = line(spark, sf).select(F.sequence(F.lit(0), F.lit(3)).alias("i"), "x", "y")
    return told(ols_sparse(src, "y", "i", "x", 4))


def ols_price_cg(spark, sf):
    """The normal equations by conjugate gradients; only products with X'X leave the rows."""
    src = line(spark, sf).select("x", "y").persist()
    xy = row_sum(src.select(F.concat("x", F.array("y")).alias("z")), "z", lambda b: (b[:, :-1].T @ b[:, -1])[:, None])[:, 0]
    scale = np.sqrt(np.diag(row_sum(src, "x", lambda b: b.T @ b)))
    b = cg_solve(lambda v: row_sum(src, "x", lambda m: (m.T @ (m @ (v / scale)))[:, None])[:, 0] / scale, xy / scale, 1e-13) / scale
    return spark.createDataFrame([(i, float(v)) for i, v in enumerate(b)], "pos int, coef double").select("pos", F.round("coef", 3).alias("coef"))


def ols_weighted(spark, sf):
    src = line(spark, sf).withColumn("w", F.element_at("x", 2)).withColumn("x", F.slice("x", 1, 2))
    return told(ols(src, "y", "x", weights="w")).select("pos", "coef")


def ols_group_brand(spark, sf):
    part = table(spark, sf, "part").select(F.col("p_partkey").alias("l_partkey"), "p_brand")
    src = line(spark, sf).withColumn("x", F.slice("x", 1, 2)).join(part, "l_partkey")
    return told(ols(src, "y", "x", by=["p_brand"], kernel="expr", d=2), ("p_brand",))


def ols_group_segment(spark, sf):
    o = table(spark, sf, "orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey").join(table(spark, sf, "customer").select(F.col("c_custkey").alias("o_custkey"), "c_mktsegment"), "o_custkey")
    src = line(spark, sf).withColumn("x", F.slice("x", 1, 2)).join(o, "l_orderkey")
    return told(ols(src, "y", "x", by=["c_mktsegment"]), ("c_mktsegment",))


def ols_rank_deficient(spark, sf):
    """A column twice over: least-norm coefficients, which share the slope as 1 : 2."""
    src = line(spark, sf).select(F.array(F.lit(1.0), F.get("x", F.lit(1)), 2 * F.get("x", F.lit(1))).alias("x"), "y")
    r = ols(src, "y", "x")
    return r.select(F.posexplode("coef").alias("pos", "c"), "rank", "d").select("pos", F.round("c", 4).alias("coef"), "rank", "d")


RANK_SQL = f"""
with s as (select regr_slope(y, x1) as b, avg(y) as my, avg(x1) as mx, count(*) as n from ({LINE_SQL})),
-- among (a, u, v) with a + (u + 2 v) x fitting, the intercept is set by the fit, so the least norm splits b = u + 2 v
f as (select my - b * mx as a, b / 5 as u, 2 * b / 5 as v from s)
select 0 as pos, round(a, 4) as coef, 2 as rank, 3 as d from f union all select 1, round(u, 4), 2, 3 from f union all select 2, round(v, 4), 2, 3 from f"""


def ols_kernels_agree(spark, sf):
    """All kernels give the numbers of the default one, but for rounding."""
    src = line(spark, sf).persist()
    base = ols(src, "y", "x").first()
    rows = []
    for k in ("rowvec", "loop", "expr", "block", "jvm"):
        r = ols(src, "y", "x", kernel=k, **({"d": 4} if k == "expr" else {})).first()
        rows.append((k, all(bool(np.allclose(base[c], r[c], rtol=1e-6, atol=1e-9)) for c in ("coef", "std_err", "r2"))))
    src.unpersist()
    return spark.createDataFrame(rows, "kernel string, agrees boolean")


def ols_simple(spark, sf):
    src = event(spark, sf).select(F.get("x", F.lit(1)).alias("v"), "y")
    return simple_ols(src, "y", "v").select(F.round("slope", 6).alias("slope"), F.round("intercept", 4).alias("intercept"), F.round("r2", 6).alias("r2"), "n")


def ols_by_gradient(spark, sf):
    """Batch gradient descent on the squared loss reaches the closed form."""
    src = doc(spark, sf).withColumn("x", F.transform("x", lambda v: v / 10)).withColumn("y", F.col("y") / 100).persist()
    exact = ols(src, "y", "x").first()
    fit = convex.fit(convex.LeastSquares(2), src, "gd", max_iter=60, tol=1e-9)
    src.unpersist()
    ok = bool(fit.log.rows[-1]["loss"] <= 1.05 * exact["sse"] / exact["n"])
    down = all(b["loss"] <= a["loss"] + 1e-12 for a, b in zip(fit.log.rows, fit.log.rows[1:]))
    return spark.createDataFrame([(ok, down)], "near_closed_form boolean, loss_never_rises boolean")


def predict_ols_docs(spark, sf):
    src = doc(spark, sf)
    b = ols(src, "y", "x").first()["coef"]
    return src.select("doc_id", F.round(predict_ols(src, "x", b), 4).alias("predicted"))


def fold_merge_invariant(spark, sf):
    """Splits of the rows over 1, 3 and 8 partitions, with the order turned round, change nothing."""
    src = line(spark, sf).select("x", "y")
    base = ols(src, "y", "x").first()
    rows = []
    for p in (1, 3, 8):
        r = ols(src.orderBy(F.desc("y")).repartition(p), "y", "x").first()
        rows.append((p, bool(np.allclose(base["coef"], r["coef"], rtol=1e-9) and np.isclose(base["r2"], r["r2"], atol=1e-12))))
    return spark.createDataFrame(rows, "parts int, same boolean")


# logistic regression -------------------------------------------------------------------------------------------------


def _coefs(spark, fit, digits=4):
    return fit.frame.select(F.posexplode("coef").alias("pos", "c"), "converged").select("pos", F.round("c", digits).alias("coef"), "converged")


def logit_toxic(spark, sf):
    return _coefs(spark, logistic(toxic(spark, sf), "y", "x"))


def logit_toxic_noisy(spark, sf):
    return _coefs(spark, logistic(toxic(spark, sf, True), "y", "x"))


def logit_return(spark, sf):
    """A null signal: the slope is near 0, and the fit converges at once."""
    src = table(spark, sf, "lineitem").select(F.array(F.lit(1.0), F.col("l_quantity") / 10).alias("x"), (F.col("l_returnflag") == "R").cast("double").alias("y"))
    return _coefs(spark, logistic(src, "y", "x"))


def logit_separable(spark, sf):
    """An insult occurs in toxic texts only: no maximum, so not converged."""
    src = toxic(spark, sf, True).drop("y").join(table(spark, sf, "labels").select("doc_id", F.col("toxic").cast("double").alias("y")), "doc_id").withColumn("x", F.slice("x", 1, 2))
    f = logistic(src, "y", "x", max_iter=60, tol=0.0, separated_at=25.0)
    return f.frame.select("converged", "status", (F.element_at("coef", 2) > 15).alias("slope_drifts"))


def logit_embed(spark, sf):
    src = table(spark, sf, "embeddings").select(F.concat(F.array(F.lit(1.0)), F.slice(F.col("embedding").cast("array<double>"), 1, 2)).alias("x"), (F.col("label") == 0).cast("double").alias("y"))
    return _coefs(spark, logistic(src, "y", "x"), 3)


def logit_grouped_lang(spark, sf):
    r = logistic_grouped(toxic(spark, sf), "y", "x", "lang")
    return r.filter("status <> 'one_class'").select("lang", F.posexplode("coef").alias("pos", "c"), "status").select("lang", "pos", F.round("c", 3).alias("coef"), "status")


def logit_many_join(spark, sf):
    """Two specifications fitted in one loop: intercept only, and with the length."""
    r = logistic_many(toxic(spark, sf), {0: [0], 1: [0, 1]}, "y", "x")
    return r.select("spec", F.posexplode("coef").alias("pos", "c")).select("spec", "pos", F.round("c", 4).alias("coef"))


def logit_solvers_agree(spark, sf):
    src = toxic(spark, sf, True).select(F.transform("x", lambda v, i: F.when(i == 2, v / 5).otherwise(v)).alias("x"), "y").persist()
    fitted = logistic(src, "y", "x", cache=False).state
    base, best = np.array(fitted["coef"]), fitted["log_likelihood"]
    rows = []
    for s, tol in (("cg", 1.0001), ("gd", 1.02)):
        got = logistic(src, "y", "x", solver=s, cache=False, max_iter=40, tol=1e-12, stepsize=8.0).state["log_likelihood"]
        rows.append((s, bool(-got <= tol * -best)))
    igd = convex.fit(convex.Logistic(3), src, "igd", "average", convex.Step.decay(0.5, 0.3), max_iter=30, tol=0.0)
    nll = lambda w: -run_fold(src, LogisticFold(w, False), ["x", "y"]).first()["loglik"]
    rows.append(("igd", bool(nll(igd.state) <= 1.05 * nll(base))))
    src.unpersist()
    return spark.createDataFrame(rows, "solver string, agrees boolean")


def logit_iteration_log(spark, sf):
    """The log-likelihood never falls from round to round."""
    f = logistic(toxic(spark, sf, True), "y", "x")
    rows = f.log.rows
    return spark.createDataFrame([(all(b["log_likelihood"] >= a["log_likelihood"] - 1e-9 for a, b in zip(rows, rows[1:])), f.converged, len(rows) == f.iterations)], "never_falls boolean, converged boolean, logged boolean")


def predict_logit(spark, sf):
    src = toxic(spark, sf)
    b = logistic(src, "y", "x").state["coef"]
    return src.select("doc_id", F.round(predict_logistic("x", b), 4).alias("p"), predict_logistic("x", b, "class").alias("c"))


def _judged(spark, sf):
    src = toxic(spark, sf)
    b = logistic(src, "y", "x").state["coef"]
    return src.select("y", F.round(predict_logistic("x", b), 4).alias("p"), (predict_logistic("x", b) >= 0.12).cast("double").alias("c"))


_JUDGED = newton_sql(TOXIC_SQL, 2, 9) + ", j as (select y, round(1 / (1 + exp(-(b9.b0 + x1 * b9.b1))), 4) as p, (1 / (1 + exp(-(b9.b0 + x1 * b9.b1))) >= 0.12)::int::double as c from d, b9)"


def eval_confusion(spark, sf):
    return E.confusion(_judged(spark, sf), "y", "c").select(F.col("truth").cast("int").alias("truth"), F.col("guess").cast("int").alias("guess"), "n")


def eval_scores(spark, sf):
    """Area under the curve, root mean squared error and accuracy of the same model."""
    j = _judged(spark, sf)
    a = E.auc(j, "y", "p").crossJoin(E.rmse(j, "y", "p")).crossJoin(E.accuracy(j, "y", "c"))  # one row each
    return a.select(*[F.round(c, 6).alias(c) for c in ("auc", "rmse", "accuracy")])


SCORES_SQL = f"""{_JUDGED}, s as (select p, sum(y) as pos, sum(1 - y) as neg from j group by 1), b as (select *, coalesce(sum(neg) over (order by p rows between unbounded preceding and 1 preceding), 0) as below from s),
a as (select sum(pos * (below + neg / 2)) / (sum(pos) * sum(neg)) as auc from b) select round(any_value(auc), 6) as auc, round(sqrt(avg((y - p) ** 2)), 6) as rmse, round(avg((y = c)::int), 6) as accuracy from j, a"""


# gradient solvers ----------------------------------------------------------------------------------------------------


def gd_square(spark, sf):
    """The mean of (x - value)^2 over all events from 1 with steps 0.25: the way to the mean value halves each round."""
    e = table(spark, sf, "events").select("value")
    p = convex.minimise_scalar(lambda x: e.agg(F.avg(2 * (F.lit(x) - F.col("value")))).first()[0], 1.0, convex.Step.const(0.25), 10)
    return spark.createDataFrame(list(enumerate(p)), "k int, x double").select("k", F.round("x", 6).alias("x"))


def _scaled(spark, sf):
    return doc(spark, sf).select(F.transform("x", lambda v, i: F.when(i == 1, v / 10).otherwise(v)).alias("x"), (F.col("y") / 100).alias("y"))


def sgd_ls(spark, sf):
    """Ten rounds of batch gradient descent on the mean squared loss, step 0.1 / k."""
    f = convex.fit(convex.LeastSquares(2), _scaled(spark, sf), "gd", stepsize=convex.Step.inv(0.1), max_iter=10, tol=0.0)
    return f.frame.select("pos", F.round("value", 6).alias("w"))


def _gd_sql(rounds: int, a: float) -> str:
    ctes = [f"d as (select x0, x1 / 10 as x1, y / 100 as y from ({DOC_SQL}))", "w0 as (select 0.0::double as w0, 0.0::double as w1)"]
    for k in range(1, rounds + 1):
        ctes.append(f"w{k} as materialized (select any_value(w0) - {a / k} * avg(2 * (x0 * w0 + x1 * w1 - y) * x0) as w0, any_value(w1) - {a / k} * avg(2 * (x0 * w0 + x1 * w1 - y) * x1) as w1 from d, w{k - 1})")
    return f"with {', '.join(ctes)} select 0 as pos, round(w0, 6) as w from w{rounds} union all select 1, round(w1, 6) from w{rounds}"


def _descends(spark, fit, last_below=1.0):
    rows = fit.log.rows
    return spark.createDataFrame([(rows[-1]["loss"] < rows[0]["loss"] * last_below, len(rows) > 0)], "loss_falls boolean, logged boolean")


def _steps_sql(src: str, d: int, rounds: int, step: float, slope: str, l2: float = 0.0, mu: float = 0.0) -> str:
    """CTEs w0 .. w{rounds} of batch gradient rounds with a fixed step. slope: the derivative of a row's loss by x.w, in
    terms of z (x.w) and y; l2 and mu: the penalties, mu by soft threshold."""
    ctes = [f"d as materialized ({src})", f"w0 as (select {', '.join(f'0.0::double as w{j}' for j in range(d))})"]
    for k in range(1, rounds + 1):
        g = [f"any_value(w{j}) - {step} * (avg(({slope}) * x{j}) + {l2} * any_value(w{j}))" for j in range(d)]
        g = [f"sign({v}) * greatest(abs({v}) - {step * mu!r}, 0)" if mu else v for v in g]
        z = " + ".join(f"x{j} * w{j}" for j in range(d))
        ctes.append(f"w{k} as materialized (select {', '.join(f'{v} as w{j}' for j, v in enumerate(g))} from (select d.*, w.*, {z} as z from d, w{k - 1} w))")
    return "with " + ", ".join(ctes)


def _weights_sql(head: str, d: int, rounds: int) -> str:
    return head + " " + " union all ".join(f"select {j} as pos, round(w{j}, 6) as w from w{rounds}" for j in range(d))


def _weights(fit):
    return fit.frame.select("pos", F.round("value", 6).alias("w"))


_S = "(2 * y - 1)"
_HINGE = f"case when {_S} * z < 1 then -{_S} else 0 end"
_LOGISTIC = f"-{_S} / (1 + exp({_S} * z))"


def sgd_lasso(spark, sf):
    """Six proximal rounds at three penalties, the heaviest of which leaves nothing."""
    src = _scaled(spark, sf).persist()
    rows = [(k, j, float(v)) for k, mu in enumerate((0.001, 0.05, 1e4)) for j, v in enumerate(convex.fit(convex.Lasso(2, mu), src, "gd", stepsize=convex.Step.const(0.1), max_iter=6, tol=0.0).state)]
    src.unpersist()
    return spark.createDataFrame(rows, "penalty int, pos int, w double").select("penalty", "pos", F.round("w", 6).alias("w"))


LASSO_SQL = " union all ".join(f"select {k} as penalty, pos, w from ({_weights_sql(_steps_sql(f'select x0, x1 / 10 as x1, y / 100 as y from ({DOC_SQL})', 2, 6, 0.1, '2 * (z - y)', mu=mu), 2, 6)})" for k, mu in enumerate((0.001, 0.05, 1e4)))


def logit_gd(spark, sf):
    """Eight rounds of batch gradient descent on the logistic loss with a squared penalty."""
    return _weights(convex.fit(convex.Logistic(3, 1e-3), toxic(spark, sf, True), "gd", stepsize=convex.Step.const(0.05), max_iter=8, tol=0.0))


def _svm_weights(spark, sf):
    return convex.fit(convex.LinearSvm(3, 1e-2), toxic(spark, sf, True), "gd", stepsize=convex.Step.const(0.02), max_iter=8, tol=0.0)


def svm_gd(spark, sf):
    """Eight rounds of batch subgradient descent on the hinge loss."""
    return _weights(_svm_weights(spark, sf))


_SVM_SQL = _steps_sql(NOISY_SQL, 3, 8, 0.02, _HINGE, 1e-2)


def predict_svm(spark, sf):
    src = toxic(spark, sf, True)
    score = predict_ols(src, "x", _svm_weights(spark, sf).state)
    return src.select("doc_id", F.round(score, 5).alias("score"), (score > 0).cast("int").alias("c"))


def logit_cg(spark, sf):
    """Conjugate gradients reach the coefficients of Newton's method."""
    src = toxic(spark, sf, True).select(F.transform("x", lambda v, i: F.when(i == 2, v / 5).otherwise(v)).alias("x"), "y")
    f = logistic(src, "y", "x", solver="cg", max_iter=200, tol=1e-14)
    return f.frame.select(F.posexplode("coef").alias("pos", "c")).select("pos", F.round("c", 2).alias("coef"))


def sgd_epochs(spark, sf):
    """A new order of rows in every epoch, against one order for all: both lower the loss to about the same."""
    src = toxic(spark, sf, True)
    last = [convex.fit(convex.Logistic(3, 1e-4), src, "igd", "average", convex.Step.decay(0.1, 0.5), max_iter=4, tol=0.0, shuffle=o).log.rows for o in ("once", "epoch")]
    return spark.createDataFrame([(all(r[-1]["loss"] < r[0]["loss"] for r in last), abs(last[0][-1]["loss"] - last[1][-1]["loss"]) < 0.1 * last[0][-1]["loss"], last[0][-1]["loss"] != last[1][-1]["loss"])], "both_fall boolean, near boolean, orders_differ boolean")


# feature vectors -----------------------------------------------------------------------------------------------------


def feat_onehot(spark, sf):
    """Status as one-hot numbers, and their products with the price."""
    o = table(spark, sf, "orders")
    hot = features.one_hot("o_orderstatus", features.categories(o, "o_orderstatus"))
    x = features.assemble(hot, features.interaction(hot, features.number(F.col("o_totalprice") / 1000)), intercept=True)
    return o.select("o_orderkey", x.alias("x")).select("o_orderkey", *[F.round(F.get("x", F.lit(i)), 5).alias(f"x{i}") for i in range(7)])


ONEHOT_SQL = "with o as (select *, (select list(s order by s) from (select distinct o_orderstatus as s from orders)) as v from orders) select o_orderkey, 1.0::double as x0, " + ", ".join(f"(o_orderstatus = v[{i}])::int::double as x{i}" for i in (1, 2, 3)) + ", " + ", ".join(f"round((o_orderstatus = v[{i}])::int * o_totalprice / 1000, 5) as x{i + 3}" for i in (1, 2, 3)) + " from o"


def feat_standardise(spark, sf):
    d = features.standardise(table(spark, sf, "part"), ["p_retailprice", "p_size"])
    return d.select("p_partkey", F.round("p_retailprice", 6).alias("price"), F.round("p_size", 6).alias("size"))


def feat_hash(spark, sf):
    x = table(spark, sf, "part").select("p_partkey", features.hashed("p_type", 16).alias("x"))
    return x.select("p_partkey", F.posexplode("x").alias("at", "v")).filter("v <> 0").select("p_partkey", F.col("at").cast("long").alias("at"), F.col("v").cast("int").alias("sign"))


HASH_SQL = f"with h as (select p_partkey, list_reduce(list_concat([17::bigint], list_transform(string_split(p_type, ''), lambda c: ascii(c)::bigint)), lambda h, c: (h * 131 + c) % {M}) as h from part) select p_partkey, h % 16 as at, case when (h // 16) % 2 = 0 then 1 else -1 end as sign from h"


def guard_finite(spark, sf):
    """Rows left, and rows that hold no finite number, by column."""
    e = table(spark, sf, "events").select("event_id", F.when(F.col("event_id") % 10 > 0, F.col("value")).alias("a"), F.array(F.col("value"), F.when(F.col("event_id") % 11 > 0, F.lit(1.0)).otherwise(F.lit(float("inf")))).alias("v"))
    kept, bad = features.guarded(e, ["v"], ["a"])
    return kept.agg(F.count("*").alias("kept"), F.lit(bad["v"]).alias("bad_v"), F.lit(bad["a"]).alias("bad_a"))


def sgd_logit(spark, sf):
    return _descends(spark, convex.fit(convex.Logistic(3, 1e-4), toxic(spark, sf, True), "igd", "average", convex.Step.decay(0.1, 0.5), max_iter=6, tol=0.0))


def sgd_svm(spark, sf):
    return _descends(spark, convex.fit(convex.LinearSvm(3, 1e-3), toxic(spark, sf, True), "minibatch", "average", convex.Step.decay(0.1, 0.5), max_iter=6, tol=0.0, batch=16))


def sgd_serial(spark, sf):
    return _descends(spark, convex.fit(convex.Logistic(3, 1e-4), toxic(spark, sf, True), "igd", "serial", convex.Step.decay(0.1, 0.5), max_iter=4, tol=0.0))


def svm_toxic(spark, sf):
    """Hinge-loss fit on the noisy label: accuracy at least that of the greater class."""
    src = toxic(spark, sf, True).persist()
    w = svm(src, "y", "x", max_iter=12).state
    score = predict_ols(src, "x", w)
    r = src.agg(F.avg(((score > 0).cast("int") == F.col("y")).cast("double")).alias("acc"), F.avg("y").alias("p")).first()
    src.unpersist()
    return spark.createDataFrame([(r["acc"] >= max(r["p"], 1 - r["p"]) - 0.02,)], "at_least_majority boolean")


def svm_embed(spark, sf):
    """Kernel machine on random features, epsilon regression and novelty on embeddings: each lowers its loss."""
    e = table(spark, sf, "embeddings").select(F.col("embedding").cast("array<double>").alias("x"), (F.col("label") == 0).cast("double").alias("y"))
    rows = []
    for task, src in (("classify", random_features(e, "x", 64, 32, 0.5)), ("regress", e), ("novelty", e)):
        f = svm(src, "y", "x", task, max_iter=12 if task != "classify" else 10, solver="gd")
        rows.append((task, f.log.rows[-1]["loss"] <= f.log.rows[0]["loss"] + 1e-12))
    return spark.createDataFrame(rows, "task string, loss_falls boolean")


def lowrank_ratings(spark, sf):
    o = table(spark, sf, "orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey")
    p = table(spark, sf, "part").select(F.col("p_partkey").alias("l_partkey"), "p_brand")
    m = table(spark, sf, "lineitem").join(o, "l_orderkey").join(p, "l_partkey").groupBy("o_custkey", "p_brand").agg((F.sum("l_quantity") / 50).alias("r"))
    f = convex.low_rank(m, "o_custkey", "p_brand", "r", 4, epochs=3, step=0.05, blocks=3)
    return _descends(spark, f)


def cg_solve_gram(spark, sf):
    """Conjugate gradients on the scaled Gram of lineitem as a table of (i, j, v)."""
    g = table(spark, sf, "lineitem").select(F.array(F.lit(1.0), F.col("l_quantity") / 25, F.col("l_discount") * 20, F.col("l_tax") * 25).alias("x"), (F.col("l_extendedprice") / 1000).alias("y"))
    z = g.select(F.posexplode("x").alias("i", "a"), "x").select("i", "a", F.posexplode("x").alias("j", "b")).groupBy("i", "j").agg(F.avg(F.col("a") * F.col("b")).alias("v"))
    b = {r["i"]: r["v"] for r in g.select(F.posexplode("x").alias("i", "a"), "y").groupBy("i").agg(F.avg(F.col("a") * F.col("y")).alias("v")).collect()}
    x = cg_solve(triple_matvec(z.persist(), 4), np.array([b[i] for i in range(4)]), 1e-12)
    return spark.createDataFrame([(i, float(v)) for i, v in enumerate(x)], "pos int, x double").select("pos", F.round("x", 4).alias("x"))


CG_SQL = ols_sql("select 1.0::double as x0, l_quantity / 25 as x1, l_discount * 20 as x2, l_tax * 25 as x3, l_extendedprice / 1000 as y from lineitem", 4)


def bootstrap_mean(spark, sf):
    src = table(spark, sf, "orders").select("o_orderkey", (F.col("o_totalprice") / 1000).alias("v"))
    return bootstrap(src, "o_orderkey", "v", 20, seed=5).select("trial", "n", F.round("mean", 4).alias("mean"))


def bootstrap_interval(spark, sf):
    src = table(spark, sf, "orders").select("o_orderkey", (F.col("o_totalprice") / 1000).alias("v"))
    s = bootstrap_summary(bootstrap(src, "o_orderkey", "v", 100, seed=5)).first()
    mean = src.agg(F.avg("v")).first()[0]
    return spark.createDataFrame([(s["low"] <= mean <= s["high"], s["trials"])], "covers_mean boolean, trials long")


def bootstrap_ols(spark, sf):
    """A slope in each of ten resamples."""
    src = doc(spark, sf).select("doc_id", F.get("x", F.lit(1)).alias("v"), "y", F.explode(F.sequence(F.lit(0), F.lit(9))).alias("trial"))
    from rowfold.operators.descriptive import poisson_times

    w = src.withColumn("w", poisson_times(uniform(F.col("doc_id"), F.col("trial"), 9), 1.0).cast("double")).withColumn("x", F.array(F.lit(1.0), F.col("v")))
    return told(ols(w.filter("w > 0"), "y", "x", by=["trial"], weights="w", kernel="expr", d=2), ("trial",)).filter("pos = 1").select("trial", "coef")


def _times_sql(u: str, most: int = 12) -> str:
    import math

    p, cum, out = math.exp(-1.0), 0.0, []
    for k in range(most):
        cum += p
        out.append(f"({u} >= {cum!r})::int")
        p *= 1.0 / (k + 1)
    return "(" + " + ".join(out) + ")"


def iteration_log(spark, sf):
    """Newton's square root of the mean order price, its states logged round by round."""
    a = table(spark, sf, "orders").agg(F.avg("o_totalprice")).first()[0]
    f = iterate(a, lambda x, i: ((x + a / x) / 2, {"state": (x + a / x) / 2}), lambda log: False, 12)
    return f.log.frame(spark).select("iteration", F.round("state", 3).alias("state"))


ITER_SQL = """with recursive a as (select avg(o_totalprice) as a from orders),
r(iteration, x) as (select 0, a from a union all select iteration + 1, (x + a / x) / 2 from r, a where iteration < 12)
select iteration, round(x, 3) as state from r where iteration > 0"""


_LOGIT = "round(b{k}, {d}) as coef"


def _newton_rows(src: str, d: int, digits: int = 4, by: str = "", extra: str = ", true as converged", rounds: int = 9) -> str:
    key = f"{by}, " if by else ""
    return newton_sql(src, d, rounds, by) + " " + " union all ".join(f"select {key}{k} as pos, round(b{k}, {digits}) as coef{extra} from b{rounds}" for k in range(d))


QUERIES = {f.__name__: f for f in (
    ols_doclen, ols_event_time, ols_price, ols_price_expr, ols_price_block, ols_price_serial, ols_price_jvm, ols_price_sparse, ols_price_cg, ols_weighted, ols_group_brand, ols_group_segment,
    ols_rank_deficient, ols_kernels_agree, ols_simple, ols_by_gradient, predict_ols_docs, fold_merge_invariant, logit_toxic, logit_toxic_noisy, logit_return, logit_separable, logit_embed,
    logit_grouped_lang, logit_many_join, logit_solvers_agree, logit_iteration_log, predict_logit, eval_confusion, eval_scores, gd_square, sgd_ls, sgd_lasso, logit_gd, logit_cg, svm_gd, predict_svm, sgd_epochs, sgd_logit, sgd_svm, sgd_serial, svm_toxic, svm_embed,
    feat_onehot, feat_standardise, feat_hash, guard_finite,
    lowrank_ratings, cg_solve_gram, bootstrap_mean, bootstrap_interval, bootstrap_ols, iteration_log,
)}

_PRICE = ols_sql(LINE_SQL, 4)
_U = uniform_sql("o_orderkey", "trial", "5")
_UD = uniform_sql("doc_id", "trial", "9")
ORACLE = {
    "ols_doclen": ols_sql(DOC_SQL, 2), "ols_event_time": ols_sql(EVENT_SQL, 2),
    **{f"ols_price{s}": _PRICE for s in ("", "_expr", "_block", "_serial", "_jvm", "_sparse")},
    "ols_price_cg": f"select pos, round(coef, 3) as coef from ({ols_sql(LINE_SQL, 4, digits=9)})",
    "ols_weighted": f"with s as ({sums_sql('select x0, x1, x1 as w, y from (' + LINE_SQL + ')', 2, weight='w')}) select 0 as pos, round((xy0 * g1_1 - xy1 * g1_0) / (g0_0 * g1_1 - g1_0 * g1_0), 4) as coef from s union all select 1, round((xy1 * g0_0 - xy0 * g1_0) / (g0_0 * g1_1 - g1_0 * g1_0), 4) from s",
    "ols_group_brand": ols_sql(f"select p_brand, x0, x1, y from ({LINE_SQL}) join part on p_partkey = l_partkey", 2, "p_brand"),
    "ols_group_segment": ols_sql(f"select c_mktsegment, x0, x1, y from ({LINE_SQL}) join orders on o_orderkey = l_orderkey join customer on c_custkey = o_custkey", 2, "c_mktsegment"),
    "ols_rank_deficient": RANK_SQL,
    "ols_kernels_agree": "select unnest(['rowvec', 'loop', 'expr', 'block', 'jvm']) as kernel, true as agrees",
    "ols_simple": f"select round(regr_slope(y, x1), 6) as slope, round(regr_intercept(y, x1), 4) as intercept, round(regr_r2(y, x1), 6) as r2, count(*) as n from ({EVENT_SQL})",
    "ols_by_gradient": "select true as near_closed_form, true as loss_never_rises",
    "predict_ols_docs": f"with d as ({DOC_SQL}), f as (select regr_slope(y, x1) as b, regr_intercept(y, x1) as a from d) select doc_id, round(a + b * x1, 4) as predicted from d, f",
    "fold_merge_invariant": "select unnest([1, 3, 8]) as parts, true as same",
    "logit_toxic": _newton_rows(TOXIC_SQL, 2), "logit_toxic_noisy": _newton_rows(NOISY_SQL, 3),
    "logit_return": _newton_rows("select 1.0::double as x0, l_quantity / 10 as x1, (l_returnflag = 'R')::int::double as y from lineitem", 2),
    "logit_separable": "select false as converged, 'separated' as status, true as slope_drifts",
    "logit_embed": _newton_rows("select 1.0::double as x0, embedding[1]::double as x1, embedding[2]::double as x2, (label = 0)::int::double as y from embeddings", 3, 3),
    "logit_grouped_lang": _newton_rows(f"select * from ({TOXIC_SQL}) where lang in (select lang from documents join labels using (doc_id) group by lang having min(toxic) < max(toxic))", 2, 3, "lang", ", 'ok' as status", 12),
    "logit_many_join": newton_sql(TOXIC_SQL, 2, 9) + ", p as (select ln(avg(y) / (1 - avg(y))) as b from d) select 0 as spec, 0 as pos, round(b, 4) as coef from p union all select 1, 0, round(b0, 4) from b9 union all select 1, 1, round(b1, 4) from b9",
    "logit_solvers_agree": "select unnest(['cg', 'gd', 'igd']) as solver, true as agrees",
    "logit_iteration_log": "select true as never_falls, true as converged, true as logged",
    "predict_logit": newton_sql(TOXIC_SQL, 2, 9) + " select doc_id, round(1 / (1 + exp(-(b9.b0 + x1 * b9.b1))), 4) as p, (1 / (1 + exp(-(b9.b0 + x1 * b9.b1))) >= 0.5)::int as c from d, b9",
    "eval_confusion": f"{_JUDGED} select y::int as truth, c::int as guess, count(*) as n from j group by all", "eval_scores": SCORES_SQL,
    "gd_square": "select i::int as k, round(m + pow(0.5::double, i) * (1 - m), 6) as x from range(0, 11) t(i), (select avg(value) as m from events)",
    "sgd_ls": _gd_sql(10, 0.1),
    **{q: "select true as loss_falls, true as logged" for q in ("sgd_logit", "sgd_svm", "sgd_serial", "lowrank_ratings")},
    "sgd_lasso": LASSO_SQL, "logit_gd": _weights_sql(_steps_sql(NOISY_SQL, 3, 8, 0.05, _LOGISTIC, 1e-3), 3, 8), "svm_gd": _weights_sql(_SVM_SQL, 3, 8),
    "predict_svm": f"{_SVM_SQL} select doc_id, round(x0 * w0 + x1 * w1 + x2 * w2, 5) as score, (x0 * w0 + x1 * w1 + x2 * w2 > 0)::int as c from d, w8",
    "logit_cg": _newton_rows(NOISY_SQL.replace("as x2,", "/ 5 as x2,"), 3, 2, extra=""), "sgd_epochs": "select true as both_fall, true as near, true as orders_differ",
    "feat_onehot": ONEHOT_SQL, "feat_hash": HASH_SQL,
    "feat_standardise": "select p_partkey, round((p_retailprice - avg(p_retailprice) over ()) / stddev_pop(p_retailprice) over (), 6) as price, round((p_size - avg(p_size) over ()) / stddev_pop(p_size) over (), 6) as size from part",
    "guard_finite": "select count(*) filter (event_id % 10 > 0 and event_id % 11 > 0 and value is not null) as kept, count(*) filter (event_id % 11 = 0 or value is null) as bad_v, count(*) filter (event_id % 10 = 0 or value is null) as bad_a from events",
    "svm_toxic": "select true as at_least_majority",
    "svm_embed": "select unnest(['classify', 'regress', 'novelty']) as task, true as loss_falls",
    "cg_solve_gram": f"select pos, coef as x from ({CG_SQL})",
    "bootstrap_mean": f"select trial::int as trial, cast(sum(t) as bigint) as n, round(sum(t * v) / sum(t), 4) as mean from (select trial, o_totalprice / 1000 as v, {_times_sql(_U)} as t from orders, range(0, 20) r(trial)) where t > 0 group by trial",
    "bootstrap_interval": "select true as covers_mean, 100 as trials",
    "bootstrap_ols": f"with d as (select trial, x1, y, {_times_sql(_UD)} as w from ({DOC_SQL}), range(0, 10) r(trial)), s as (select trial, sum(w) as n, sum(w * x1) as sx, sum(w * x1 * x1) as sxx, sum(w * y) as sy, sum(w * x1 * y) as sxy from d group by trial) select trial::int as trial, round((sxy - sx * sy / n) / (sxx - sx * sx / n), 4) as coef from s",
    "iteration_log": ITER_SQL,
}
