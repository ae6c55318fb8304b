"""Clustering, classifiers, factorisation, topics and rules."""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

from rowfold.core.driver import drop_stage, release, stage
from rowfold.operators import kmeans as km
from rowfold.operators.supervised import gaussian_fit, naive_bayes_fit, naive_bayes_predict, naive_bayes_text, split_scores, tree_fit, tree_predict, tree_rules, tree_table
from rowfold.operators.textops import document_terms
from rowfold.operators.unsupervised import association_rules, block_multiply, block_transpose, frequent_itemsets, lda, lda_predict, left_vectors, svd
from rowfold.queries.base import table

ROUNDS, K = 4, 3


def points2(spark, sf):
    """(id, x): balance in thousands and number of orders of each customer."""
    o = table(spark, sf, "orders").groupBy(F.col("o_custkey").alias("c_custkey")).agg(F.count("*").alias("n"))
    c = table(spark, sf, "customer").join(o, "c_custkey", "left")
    return c.select(F.col("c_custkey").alias("id"), F.array(F.col("c_acctbal") / 1000, F.coalesce("n", F.lit(0)).cast("double")).alias("x"))


POINTS_SQL = "select c_custkey as id, c_acctbal / 1000 as x0, coalesce(n, 0)::double as x1 from customer left join (select o_custkey, count(*) as n from orders group by 1) on o_custkey = c_custkey"


def _lloyd_sql(rounds: int) -> str:
    """CTEs c0 .. c{rounds} (centre, x0, x1) and, for each round, its assignments and log."""
    ctes = [f"p as materialized ({POINTS_SQL})", f"c0 as materialized (select row_number() over (order by id) - 1 as centre, x0, x1 from p order by id limit {K})"]
    for i in range(1, rounds + 1):
        ctes.append(f"a{i} as materialized (select id, p.x0, p.x1, arg_min(centre, round((p.x0 - c.x0) ** 2 + (p.x1 - c.x1) ** 2, 10) * 1000 + centre * 1e-9) as centre, min((p.x0 - c.x0) ** 2 + (p.x1 - c.x1) ** 2) as d from p, c{i - 1} c group by id, p.x0, p.x1)")
        ctes.append(f"c{i} as materialized (select c.centre, coalesce(m.x0, c.x0) as x0, coalesce(m.x1, c.x1) as x1 from c{i - 1} c left join (select centre, avg(x0) as x0, avg(x1) as x1 from a{i} group by centre) m using (centre))")
    return "with " + ", ".join(ctes)


def _points_rows(fit):
    return fit.frame.select("centre", F.posexplode("point").alias("pos", "v")).select("centre", "pos", F.round("v", 5).alias("value"))


def _fit2(spark, sf, assign, **kw):
    src = points2(spark, sf)
    init = np.array([r["x"] for r in src.orderBy("id").limit(K).collect()])
    return km.kmeans(src, "x", K, "id", assign, init=init, max_iter=ROUNDS, min_frac_reassigned=-1, **kw)


def kmeans_points_implicit(spark, sf):
    return _points_rows(_fit2(spark, sf, "implicit"))


def kmeans_points_explicit(spark, sf):
    return _points_rows(_fit2(spark, sf, "explicit"))


def kmeans_points_delta(spark, sf):
    return _points_rows(_fit2(spark, sf, "explicit", stage_mode="delta"))


def kmeans_points_fused(spark, sf):
    return _points_rows(_fit2(spark, sf, "fused"))


_CENTRES = _lloyd_sql(ROUNDS) + f" select centre::int as centre, 0 as pos, round(x0, 5) as value from c{ROUNDS} union all select centre::int, 1, round(x1, 5) from c{ROUNDS}"


def kmeans_reassign_log(spark, sf):
    """Objective and rows that changed centre, round by round."""
    f = _fit2(spark, sf, "fused")
    return f.log.frame(spark).select("iteration", F.round("objective", 3).alias("objective"), F.col("moved").cast("long").alias("moved"), F.col("evaluations").cast("long").alias("evaluations"))


_LOG = _lloyd_sql(ROUNDS) + " " + " union all ".join(
    f"select {i} as iteration, round(sum(a.d), 3) as objective, {'count(*)' if i == 1 else f'count(*) filter (a.centre <> b.centre)'} as moved, count(*) * {K} as evaluations from a{i} a{'' if i == 1 else f' join a{i - 1} b using (id)'}" for i in range(1, ROUNDS + 1)
)


def kmeans_passes(spark, sf):
    """Passes over the rows and distances per row and centre: implicit 1 and 2, explicit 2 and 1, fused 1 and 1."""
    n = table(spark, sf, "customer").count()
    rows = []
    for a in ("implicit", "explicit", "fused"):
        r = _fit2(spark, sf, a).log.rows[-1]
        rows.append((a, r["passes"], r["evaluations"] // (n * K)))
    return spark.createDataFrame(rows, "variant string, passes int, distances long")


def _embed(spark, sf):
    return table(spark, sf, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("x"), "label")


def kmeans_embed(spark, sf):
    """Two rounds on the whole vectors, from the three of least id."""
    src = _embed(spark, sf)
    init = np.array([r["x"] for r in src.orderBy("vec_id").limit(3).collect()])
    return _points_rows(km.kmeans(src, "x", 3, "vec_id", "fused", init=init, max_iter=2, min_frac_reassigned=-1))


_EMBED_SQL = "with p as materialized (select vec_id, embedding::double[] as x from embeddings), c0 as materialized (select row_number() over (order by vec_id) - 1 as centre, x from p order by vec_id limit 3), " + ", ".join(
    f"a{i} as materialized (select vec_id, any_value(p.x) as x, arg_min(centre, list_distance(p.x, c.x)) as centre from p, c{i - 1} c group by vec_id), c{i} as materialized (select centre, list(m order by i) as x from (select centre, i, avg(x[i]) as m from a{i}, range(1, 65) t(i) group by all) group by 1)"
    for i in (1, 2)
) + " select centre::int as centre, i::int - 1 as pos, round(x[i], 5) as value from c2, range(1, 65) t(i)"


def kmeans_embed_descends(spark, sf):
    """Lloyd's objective never rises, for every seeding."""
    src = _embed(spark, sf).persist()
    rows = []
    for m in ("first", "random", "plusplus", "parallel"):
        f = km.kmeans(src, "x", 5, "vec_id", seed_method=m, max_iter=4, min_frac_reassigned=-1)
        o = [r["objective"] for r in f.log.rows]
        rows.append((m, all(b <= a + 1e-6 for a, b in zip(o, o[1:]))))
    src.unpersist()
    return spark.createDataFrame(rows, "seeding string, never_rises boolean")


def kmeans_distances(spark, sf):
    """Other distances run and stop; an empty centre is kept or reseeded."""
    src = points2(spark, sf).persist()
    rows = [(d, km.kmeans(src, "x", 2, "id", distance=d, seed_method="first", max_iter=3).iterations > 0) for d in ("l1", "cosine", "tanimoto")]
    far = np.array([[0.0, 10.0], [9e9, 9e9]])
    kept = km.kmeans(src, "x", 2, "id", init=far, max_iter=2, min_frac_reassigned=-1)
    moved = km.kmeans(src, "x", 2, "id", init=far, max_iter=2, min_frac_reassigned=-1, empty="reseed")
    rows += [("keep", bool(kept.state[1, 0] == 9e9)), ("reseed", bool(moved.state[1, 0] < 1e6))]
    src.unpersist()
    return spark.createDataFrame(rows, "what string, holds boolean")


def predict_kmeans(spark, sf):
    src = points2(spark, sf)
    c = _fit2(spark, sf, "implicit").state
    return km.predict_kmeans(src, "x", c).select("id", "cid", F.round("dist", 4).alias("dist"))


_PREDICT_KM = _lloyd_sql(ROUNDS) + f" select id, arg_min(c.centre, round((p.x0 - c.x0) ** 2 + (p.x1 - c.x1) ** 2, 10))::int as cid, round(min((p.x0 - c.x0) ** 2 + (p.x1 - c.x1) ** 2), 4) as dist from p, c{ROUNDS} c group by id"


def kmeans_quality(spark, sf):
    """Purity against labels, and the silhouette, lie in their ranges."""
    src = _embed(spark, sf)
    f = km.kmeans(src, "x", 10, "vec_id", seed_method="plusplus", max_iter=8)
    p = km.predict_kmeans(src, "x", f.state)
    a, b = km.purity(p, "cid", "label").first()[0], km.silhouette(p, "x", "cid").first()[0]
    return spark.createDataFrame([(0.1 <= a <= 1, -1 <= b <= 1)], "purity_in_range boolean, silhouette_in_range boolean")


# naive Bayes ---------------------------------------------------------------------------------------------------------


def _orders(spark, sf):
    o = table(spark, sf, "orders").join(table(spark, sf, "customer").select(F.col("c_custkey").alias("o_custkey"), "c_mktsegment"), "o_custkey")
    return o.select("o_orderkey", F.col("o_orderstatus").alias("cls"), F.col("o_orderpriority").alias("prio"), F.col("c_mktsegment").alias("seg"), "o_totalprice")


ORDERS_SQL = "select o_orderkey, o_orderstatus as cls, o_orderpriority as prio, c_mktsegment as seg, o_totalprice from orders join customer on c_custkey = o_custkey"


def nb_categorical(spark, sf):
    _, c = naive_bayes_fit(_orders(spark, sf), "cls", ["prio", "seg"])
    return c.select("class", "attr", "value", "n", F.round("logp", 6).alias("logp"))


NB_SQL = f"""
with d as ({ORDERS_SQL}), p as (select cls, 'prio' as attr, prio as value from d union all select cls, 'seg', seg from d),
c as (select cls as class, count(*) as nc from d group by 1), v as (select attr, value, count(*) over (partition by attr) as k from (select distinct attr, value from p)),
n as (select cls, attr, value, count(*) as n from p group by all)
select class, v.attr, v.value, coalesce(n.n, 0) as n, round(ln((coalesce(n.n, 0) + 1) / (nc + k)::double), 6) as logp
from c cross join v left join n on n.cls = class and n.attr = v.attr and n.value = v.value"""


def nb_gaussian(spark, sf):
    g = gaussian_fit(_orders(spark, sf).withColumn("price", F.col("o_totalprice") / 1000), "cls", ["price"])
    return g.select("class", "n", "attr", F.round("mean", 4).alias("mean"), F.round("var", 3).alias("var"))


def _toxic_terms(spark, sf):
    d = table(spark, sf, "documents").join(table(spark, sf, "labels").select("doc_id", "toxic"), "doc_id")
    t = d.select("doc_id", F.col("toxic").cast("string").alias("cls"), F.explode(F.regexp_extract_all(F.lower("text"), F.lit("([a-z]+)"), F.lit(1))).alias("token"))
    return t


def nb_text(spark, sf):
    _, m = naive_bayes_text(_toxic_terms(spark, sf), "cls")
    return m.select("class", "token", "n", F.round("logp", 6).alias("logp"))


NB_TEXT_SQL = """
with t as (select toxic::varchar as class, unnest(regexp_extract_all(lower(text), '[a-z]+')) as token from documents join labels using (doc_id)),
c as (select class, token, count(*) as n from t group by all), s as (select class, sum(n) as t from c group by 1), v as (select count(distinct token) as v from t)
select class, token, n, round(ln((n + 1) / (s.t + v.v)::double), 6) as logp from c join s using (class), v
union all select class, null, 0, round(ln(1 / (t + v.v)::double), 6) from s, v"""


def predict_nb(spark, sf):
    src = _orders(spark, sf)
    pr, c = naive_bayes_fit(src, "cls", ["prio", "seg"])
    pairs = src.select("o_orderkey", F.explode(F.array(F.struct(F.lit("prio").alias("attr"), F.col("prio").alias("value")), F.struct(F.lit("seg").alias("attr"), F.col("seg").alias("value")))).alias("p")).select("o_orderkey", "p.*")
    return naive_bayes_predict(src, "o_orderkey", pairs, pr, c).filter("rank = 1").select("o_orderkey", F.round("score", 5).alias("score"))


PREDICT_NB_SQL = f"""
with d as ({ORDERS_SQL}), m as ({NB_SQL.replace('round(ln((coalesce(n.n, 0) + 1) / (nc + k)::double), 6)', 'ln((coalesce(n.n, 0) + 1) / (nc + k)::double)')}),
pr as (select cls as class, ln(count(*) / (select count(*) from d)::double) as p from d group by 1)
select o_orderkey, round(max(p + a.logp + b.logp), 5) as score from d cross join pr join m a on a.class = pr.class and a.attr = 'prio' and a.value = prio join m b on b.class = pr.class and b.attr = 'seg' and b.value = seg group by 1"""


# trees ---------------------------------------------------------------------------------------------------------------


def _flags(spark, sf):
    return table(spark, sf, "documents").select("doc_id", F.col("lang").alias("cls"), F.col("text").rlike("(?i)the ").cast("string").alias("the"), F.col("text").rlike("(?i)der ").cast("string").alias("der"), F.col("text").contains("ê").cast("string").alias("circ"), (F.col("n_chars") / 1000).alias("len"))


FLAGS_SQL = "select doc_id, lang as cls, regexp_matches(text, '(?i)the ')::varchar as the, regexp_matches(text, '(?i)der ')::varchar as der, contains(text, 'ê')::varchar as circ from documents"


def _root_gain(spark, sf, criterion):
    src = _flags(spark, sf)
    each = F.explode(F.array(*[F.struct(F.lit(a).alias("attr"), F.col(a).alias("value")) for a in ("the", "der", "circ")]))
    counts = src.select(F.lit(0).alias("node"), "cls", each.alias("p")).groupBy("node", "p.attr", "p.value", "cls").agg(F.count("*").alias("n"))
    return split_scores(counts, criterion).select("attr", "n", F.round("gain", 6).alias("gain"), F.round("score", 6).alias("score"))


def tree_root_gain(spark, sf):
    return _root_gain(spark, sf, "gainratio")


def tree_root_infogain(spark, sf):
    return _root_gain(spark, sf, "infogain")


def tree_root_gini(spark, sf):
    return _root_gain(spark, sf, "gini")


_PAIRS = f"with d as ({FLAGS_SQL}), p as (select cls, 'the' as attr, the as value from d union all select cls, 'der', der from d union all select cls, 'circ', circ from d), vc as (select attr, value, cls, count(*)::double as n from p group by all), v as (select attr, value, sum(n) as nv, -sum(n * log2(n)) as e, sum(n * n) as q from vc group by all), t as (select attr, sum(n) as nn from vc group by 1), c as (select attr, sum(nc * log2(nc)) as ec, sum(nc * nc) as qc from (select attr, cls, sum(n) as nc from vc group by all) group by 1), a as (select attr, sum(e + nv * log2(nv)) as w, sum(nv * log2(nv)) as ev, sum(q / nv) as gw from v group by 1)"
_ENT = "log2(nn) - ec / nn - w / nn"
ROOT_SQL = f"{_PAIRS} select attr, nn::bigint as n, round({_ENT}, 6) as gain, round(case when log2(nn) - ev / nn > 1e-12 then ({_ENT}) / (log2(nn) - ev / nn) else 0 end, 6) as score from t join c using (attr) join a using (attr)"
INFO_SQL = f"{_PAIRS} select attr, nn::bigint as n, round({_ENT}, 6) as gain, round({_ENT}, 6) as score from t join c using (attr) join a using (attr)"
GINI_SQL = f"{_PAIRS} select attr, nn::bigint as n, round(gw / nn - qc / (nn * nn), 6) as gain, round(gw / nn - qc / (nn * nn), 6) as score from t join c using (attr) join a using (attr)"


def _tree(spark, sf, **kw):
    return tree_fit(_flags(spark, sf), "cls", ["the", "der", "circ"], ["len"], max_depth=3, bins=8, **kw)


def tree_c45(spark, sf):
    return tree_table(spark, _tree(spark, sf)).select("node_id", "parent", "depth", "attr", "kind", "branch", "class", F.round("n", 3).alias("n"), "leaf")


def tree_variants(spark, sf):
    """Accuracy on the training rows is never below that of the greatest class, whatever the criterion, pruning or rule for
    missing values; pruning never adds nodes."""
    src = _flags(spark, sf).withColumn("the", F.when(F.pmod("doc_id", F.lit(7)) > 0, F.col("the"))).persist()
    top = src.groupBy("cls").count().agg(F.max("count") / F.sum("count")).first()[0]
    full = None
    rows = []
    for name, kw in (("gainratio", {}), ("infogain", {"criterion": "infogain"}), ("gini", {"criterion": "gini"}), ("fraction", {"missing": "fraction"}), ("ebp", {"prune": "ebp"}), ("rep", {"prune": "rep", "holdout": src})):
        nodes = tree_fit(src, "cls", ["the", "der", "circ"], ["len"], max_depth=3, bins=8, **kw)
        acc = tree_predict(src, nodes).agg(F.avg((F.col("predicted") == F.col("cls")).cast("double"))).first()[0]
        leaves = len(tree_rules(nodes))
        full = full or leaves
        rows.append((name, acc >= top - 1e-9, leaves <= full if name in ("ebp", "rep") else True))
    src.unpersist()
    return spark.createDataFrame(rows, "variant string, at_least_majority boolean, no_larger boolean")


def predict_tree(spark, sf):
    return tree_predict(_flags(spark, sf), _tree(spark, sf)).select("doc_id", "predicted")


# factorisation -------------------------------------------------------------------------------------------------------


def _svd(spark, sf, method):
    s, _ = svd(_embed(spark, sf), "x", 3, method, power_iters=30)
    exact, _ = svd(_embed(spark, sf), "x", 3)
    return spark.createDataFrame([(i, bool(abs(s[i] - exact[i]) <= 1e-3 * exact[0])) for i in range(3)], "pos int, near_exact boolean")


def svd_gram(spark, sf):
    """All squared singular values add up to the sum of squares; left vectors have unit length."""
    src = _embed(spark, sf)
    s, v = svd(src, "x", 64)
    u = left_vectors(src, "x", s[:2], v[:, :2]).agg(F.sum(F.get("u", F.lit(0)) ** 2).alias("a"), F.sum(F.get("u", F.lit(1)) ** 2).alias("b")).first()
    return spark.createDataFrame([(float((s * s).sum()), float(u["a"]), float(u["b"]))], "energy double, u0 double, u1 double").select(F.round("energy", 3).alias("energy"), F.round("u0", 6).alias("u0"), F.round("u1", 6).alias("u1"))


def svd_random(spark, sf):
    return _svd(spark, sf, "random")


def svd_lanczos(spark, sf):
    return _svd(spark, sf, "lanczos")


def blockmat_gram(spark, sf):
    """X'X of the first four components, by transposing and multiplying blocks of 64 rows."""
    e = table(spark, sf, "embeddings").select("vec_id", F.slice(F.col("embedding").cast("array<double>"), 1, 4).alias("x"))
    b = e.groupBy(F.floor(F.col("vec_id") / 64).cast("int").alias("bi")).agg(F.flatten(F.transform(F.array_sort(F.collect_list(F.struct("vec_id", "x"))), lambda s: s["x"])).alias("data"), F.count("*").cast("int").alias("rows"))
    m = b.select("bi", F.lit(0).alias("bj"), "rows", F.lit(4).alias("cols"), "data")
    g = block_multiply(block_transpose(m), m)
    return g.select(F.posexplode("data").alias("p", "v")).select(F.floor(F.col("p") / 4).cast("int").alias("i"), F.pmod("p", F.lit(4)).cast("int").alias("j"), F.round("v", 4).alias("v"))


BLOCK_SQL = "with p as (select vec_id, i::int - 1 as i, embedding[i]::double as v from embeddings, range(1, 5) t(i)) select a.i, b.i as j, round(sum(a.v * b.v), 4) as v from p a join p b using (vec_id) group by all"


LEAST = 5


def lda_topics(spark, sf):
    """Topic counts keep every token of the terms of five documents, and both samplers raise the likelihood."""
    t = stage(document_terms(table(spark, sf, "documents"), "doc_id", "text"), "terms")
    each = t.select(F.explode(F.arrays_zip("terms", "counts")).alias("p")).groupBy("p.terms").agg(F.count("*").alias("df"), F.sum("p.counts").alias("n"))
    total = each.filter(F.col("df") >= LEAST).agg(F.sum("n")).first()[0]
    rows = []
    for m in ("gibbs", "vb"):
        f = lda(t, 4, iters=4, method=m, least_docs=LEAST)
        drop_stage(f.state)
        release(spark)
        rows.append((m, abs(f.frame.agg(F.sum("n")).first()[0] - total) < 1e-3 * total, f.log.rows[-1]["log_likelihood"] > f.log.rows[0]["log_likelihood"]))
    return spark.createDataFrame(rows, "method string, tokens_kept boolean, likelihood_rises boolean")


def lda_inference(spark, sf):
    """Topic shares of documents add up to 1."""
    t = stage(document_terms(table(spark, sf, "documents"), "doc_id", "text"), "terms")
    f = lda(t, 3, iters=2, method="vb", least_docs=LEAST)
    return lda_predict(t, f.frame, 3).groupBy("doc_id").agg(F.round(F.sum("share"), 6).alias("total"))


# rules ---------------------------------------------------------------------------------------------------------------


def _baskets(spark, sf):
    return table(spark, sf, "lineitem").join(table(spark, sf, "part").select(F.col("p_partkey").alias("l_partkey"), "p_type"), "l_partkey").select("l_orderkey", "p_type")


def _level(spark, sf, k):
    return frequent_itemsets(_baskets(spark, sf), "l_orderkey", "p_type", 0.01, k).filter(F.size("items") == k).select(F.array_join("items", "|").alias("items"), "n", F.round("support", 6).alias("support"))


def assoc_items(spark, sf):
    return _level(spark, sf, 1)


def assoc_pairs(spark, sf):
    return _level(spark, sf, 2)


def assoc_pairs_fpgrowth(spark, sf):
    """The engine's own pattern growth finds the same pairs."""
    from pyspark.ml.fpm import FPGrowth

    b = _baskets(spark, sf).groupBy("l_orderkey").agg(F.collect_set("p_type").alias("items"))
    n = b.count()
    f = FPGrowth(itemsCol="items", minSupport=0.01).fit(b).freqItemsets.filter(F.size("items") == 2)
    return f.select(F.array_join(F.array_sort("items"), "|").alias("items"), F.col("freq").alias("n"), F.round(F.col("freq") / n, 6).alias("support"))


def assoc_triples(spark, sf):
    return _level(spark, sf, 3)


def assoc_rules(spark, sf):
    r = association_rules(frequent_itemsets(_baskets(spark, sf), "l_orderkey", "p_type", 0.05, 2), 0.1)
    return r.select(F.array_join("lhs", "|").alias("lhs"), F.array_join("rhs", "|").alias("rhs"), "n", F.round("confidence", 6).alias("confidence"), F.round("lift", 6).alias("lift"), F.round("conviction", 6).alias("conviction"))


_B = "b as (select distinct l_orderkey as k, p_type as i from lineitem join part on p_partkey = l_partkey), t as (select count(distinct k) as t from b)"


def _level_sql(k: int) -> str:
    join = " ".join(f"join b b{i} on b{i}.k = b0.k and b{i}.i > b{i - 1}.i" for i in range(1, k))
    items = " || '|' || ".join(f"b{i}.i" for i in range(k))
    return f"with {_B} select {items} as items, count(*) as n, round(count(*) / any_value(t.t)::double, 6) as support from b b0 {join}, t group by 1 having count(*) >= ceil(0.01 * any_value(t.t) - 1e-9)"


RULES_SQL = f"""
with {_B}, one as (select i, count(*)::double as n from b group by 1), p as (select a.i as lhs, c.i as rhs, count(*) as n from b a join b c on a.k = c.k and a.i <> c.i group by all)
select lhs, rhs, p.n, round(p.n / l.n, 6) as confidence, round(p.n / l.n / (r.n / t.t), 6) as lift, round((1 - r.n / t.t) / nullif(1 - p.n / l.n, 0), 6) as conviction
from p join one l on l.i = lhs join one r on r.i = rhs, t where p.n >= ceil(0.05 * t.t - 1e-9) and p.n / l.n >= 0.1"""


QUERIES = {f.__name__: f for f in (
    kmeans_points_implicit, kmeans_points_explicit, kmeans_points_delta, kmeans_points_fused, kmeans_reassign_log, kmeans_passes, kmeans_embed, kmeans_embed_descends, kmeans_distances, predict_kmeans,
    kmeans_quality, nb_categorical, nb_gaussian, nb_text, predict_nb, tree_root_gain, tree_root_infogain, tree_root_gini, tree_c45, tree_variants, predict_tree, svd_gram, svd_random, svd_lanczos,
    blockmat_gram, lda_topics, lda_inference, assoc_items, assoc_pairs, assoc_pairs_fpgrowth, assoc_triples, assoc_rules,
)}

ORACLE = {
    **{f"kmeans_points_{v}": _CENTRES for v in ("implicit", "explicit", "delta", "fused")},
    "kmeans_reassign_log": _LOG,
    "kmeans_passes": "select * from (values ('implicit', 1, 2::bigint), ('explicit', 2, 1::bigint), ('fused', 1, 1::bigint)) t(variant, passes, distances)",
    "kmeans_embed_descends": "select unnest(['first', 'random', 'plusplus', 'parallel']) as seeding, true as never_rises",
    "kmeans_distances": "select unnest(['l1', 'cosine', 'tanimoto', 'keep', 'reseed']) as what, true as holds",
    "predict_kmeans": _PREDICT_KM,
    "kmeans_quality": "select true as purity_in_range, true as silhouette_in_range",
    "nb_categorical": NB_SQL,
    "nb_gaussian": f"select cls as class, count(*) as n, 'price' as attr, round(avg(o_totalprice / 1000), 4) as mean, round(var_samp(o_totalprice / 1000), 3) as var from ({ORDERS_SQL}) group by 1",
    "nb_text": NB_TEXT_SQL, "predict_nb": PREDICT_NB_SQL,
    "tree_root_gain": ROOT_SQL, "tree_root_infogain": INFO_SQL, "tree_root_gini": GINI_SQL,
    "tree_variants": "select variant, true as at_least_majority, true as no_larger from (select unnest(['gainratio', 'infogain', 'gini', 'fraction', 'ebp', 'rep']) as variant)",
    "svd_gram": "select round(sum(list_sum(list_transform(embedding, lambda v: v::double * v::double))), 3) as energy, 1.0::double as u0, 1.0::double as u1 from embeddings",
    **{q: "select unnest([0, 1, 2]) as pos, true as near_exact" for q in ("svd_random", "svd_lanczos")},
    "blockmat_gram": BLOCK_SQL,
    "lda_topics": "select unnest(['gibbs', 'vb']) as method, true as tokens_kept, true as likelihood_rises",
    "lda_inference": "with t as (select doc_id, unnest(regexp_extract_all(lower(text), '[a-z]+')) as term from documents), c as (select term from t group by 1 having count(distinct doc_id) >= 5) select distinct doc_id, 1.0::double as total from t join c using (term)",
    "assoc_items": _level_sql(1), "assoc_pairs": _level_sql(2), "assoc_pairs_fpgrowth": _level_sql(2), "kmeans_embed": _EMBED_SQL, "assoc_triples": _level_sql(3), "assoc_rules": RULES_SQL,
}
