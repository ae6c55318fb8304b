"""Distribution functions, folds, regression and the methods that need no tables."""

import itertools
import math
import random

import numpy as np
import pyarrow as pa
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from rowfold.core import validate
from rowfold.core.driver import below, iterate
from rowfold.core.fold import check_fold
from rowfold.functions import dist, sparse
from rowfold.operators import chains, convex, tasks, textops
from rowfold.operators.descriptive import cg_solve, dyadic_cover
from rowfold.operators.kmeans import distances, nearest
from rowfold.operators.ols import OlsFold, ols, solve
from rowfold.operators.supervised import _score


def test_t_tail_of_the_worked_example():
    assert dist.t_two_sided(5.3127, 98) == pytest.approx(6.7685e-07, rel=1e-3)
    assert dist.t_two_sided(42.064, 98) < 1e-15
    t = 42.064
    assert t * t / (t * t + 98) == pytest.approx(0.9475, abs=5e-5)


def test_distribution_identities():
    assert dist.norm_cdf(1.959963985) == pytest.approx(0.975, abs=1e-9)
    assert dist.chi2_sf(3.841458821, 1) == pytest.approx(0.05, abs=1e-9)
    assert dist.f_sf(4.0, 1, 30) == pytest.approx(dist.t_two_sided(2.0, 30), rel=1e-12)
    assert dist.chi2_cdf(5, 3) + dist.chi2_sf(5, 3) == pytest.approx(1, abs=1e-14)
    assert dist.quantile(dist.norm_cdf, 0.9) == pytest.approx(1.2815515655, abs=1e-8)
    assert dist.norm_two_sided(38) == pytest.approx(2 * dist.norm_sf(38), rel=1e-12)


def _batch(x, y):
    return pa.RecordBatch.from_arrays([pa.array([list(map(float, r)) for r in x], pa.list_(pa.float64())), pa.array(np.asarray(y, float))], names=["x", "y"])


def test_ols_against_lstsq_and_by_kernel():
    rng = np.random.default_rng(0)
    x = np.column_stack([np.ones(60), rng.normal(size=(60, 3))])
    y = x @ [1, 2, -1, 0.5] + rng.normal(size=60) * 0.1
    want = np.linalg.lstsq(x, y, rcond=None)[0]
    for k in ("blas", "loop", "rowvec"):
        f = OlsFold(k)
        r = f.finish(f.step(f.zero(), _batch(x, y)))[0]
        assert np.allclose(r["coef"], want, rtol=1e-9)
        assert np.allclose(x.T @ (y - x @ np.array(r["coef"])), 0, atol=1e-9)
        assert np.allclose(np.array(r["coef"]) / r["std_err"], r["t_stats"])


def test_ols_without_full_rank_has_least_norm():
    x = np.column_stack([np.ones(20), np.arange(20.0), 2 * np.arange(20.0)])
    y = 3 + 5 * np.arange(20.0)
    r = solve(20, y.sum(), y @ y, x.T @ y, x.T @ x, 20)
    assert r["rank"] == 2 and np.allclose(r["coef"], np.linalg.pinv(x) @ y)


@settings(max_examples=20, deadline=None)
@given(st.lists(st.tuples(st.floats(-5, 5), st.floats(-5, 5)), min_size=4, max_size=30))
def test_merge_invariant(rows):
    x = [(1.0, a) for a, _ in rows]
    same = lambda a, b: np.allclose(a[0]["sse"], b[0]["sse"], atol=1e-6) and a[0]["n"] == b[0]["n"]
    assert check_fold(OlsFold(), _batch(x, [b for _, b in rows]), same)


def test_iterate_and_gradient_toy():
    f = iterate(1.0, lambda x, i: (x - 0.1 * 2 * x, {"size": abs(x)}), below("size", 1e-3), 200)
    assert f.converged and abs(f.state) < 1e-3
    path = convex.minimise_scalar(lambda x: 2 * x, 1.0, convex.Step.inv(0.4), 50)
    assert abs(path[-1]) < abs(path[0])


def test_gradients_match_differences():
    rng = np.random.default_rng(1)
    x, y = rng.normal(size=(12, 3)), rng.integers(0, 2, 12).astype(float)
    for obj in (convex.LeastSquares(3), convex.Logistic(3), convex.LinearSvm(3, 0), convex.InsensitiveRegression(3, 0.1, 0)):
        w = rng.normal(size=3)
        g = obj.grad(w, (x, y))
        for i in range(3):
            e = np.eye(3)[i] * 1e-6
            assert (obj.loss(w + e, (x, y)) - obj.loss(w - e, (x, y))) / 2e-6 == pytest.approx(g[i], abs=1e-3)


def test_soft_threshold():
    assert convex.Lasso(2, 1.0).prox(np.array([0.5, -3.0]), 1.0).tolist() == [0.0, -2.0]


def test_lloyd_against_all_partitions():
    x = np.array([[0.0], [1], [2], [10], [11], [12], [30], [31]])
    best = min(sum(((x[list(g)] - x[list(g)].mean(0)) ** 2).sum() for g in p) for p in _two(range(8)))
    c = np.array([[0.0], [30]])
    for _ in range(10):
        at, _d = nearest(x, c)
        c = np.array([x[at == k].mean(0) for k in range(2)])
    assert distances(x, c).min(1).sum() >= best - 1e-9


def _two(items):
    items = list(items)
    for m in range(1, 2 ** (len(items) - 1)):
        a = [i for k, i in enumerate(items) if m >> k & 1]
        yield a, [i for i in items if i not in a]


def test_chain_against_enumeration():
    rng = np.random.default_rng(2)
    for _ in range(20):
        e, t = rng.normal(size=(4, 3)), rng.normal(size=(3, 3))
        score = lambda y: e[range(4), y].sum() + sum(t[a, b] for a, b in zip(y, y[1:]))  # noqa: E731, B023
        every = sorted(((score(y), list(y)) for y in itertools.product(range(3), repeat=4)), reverse=True)
        assert chains.viterbi_numpy(e, t)[1] == every[0][1]
        top = chains.viterbi_top(e, t, 5)
        assert [p for _, p in top] == [p for _, p in every[:5]]
        z, p, pairs = chains.marginals(e, t)
        assert z == pytest.approx(math.log(sum(math.exp(s) for s, _ in every)))
        want = sum(math.exp(s - z) for s, y in every if y[2] == 1)
        assert p[2, 1] == pytest.approx(want) and pairs.sum() == pytest.approx(3)


def test_gibbs_near_exact():
    rng = np.random.default_rng(3)
    e, t = rng.normal(size=(5, 3)), rng.normal(size=(3, 3))
    _, p, _ = chains.marginals(e, t)
    c = chains.gibbs_chain(e, t, 4000, 200, 1, rng)
    assert np.abs(c / c.sum(1, keepdims=True) - p).max() < 0.05
    m, taken = chains.mh_chain(e, t, 4000, 200, 1, rng)
    assert np.abs(m / m.sum(1, keepdims=True) - p).max() < 0.06 and 0 < taken < 1


def test_run_lengths():
    r, v = sparse.encode(np.array([0, 0, 0, 2.0, 2, 5]))
    assert r.tolist() == [3, 2, 1] and v.tolist() == [0, 2, 5]
    a, b = np.array([0, 0, 1.0, 1]), np.array([2.0, 2, 2, 3])
    r, v = sparse.merge_runs(*sparse.encode(a), *sparse.encode(b), np.multiply)
    assert np.repeat(v, r).tolist() == (a * b).tolist()
    with pytest.raises(ValueError):
        sparse.merge_runs(*sparse.encode(a), *sparse.encode(b[:3]), np.add)


def test_conjugate_gradients():
    rng = np.random.default_rng(4)
    m = rng.normal(size=(6, 6))
    m = m @ m.T + np.eye(6)
    b = rng.normal(size=6)
    assert np.allclose(cg_solve(lambda v: m @ v, b, 1e-12), np.linalg.solve(m, b))


def test_dyadic_cover():
    for _ in range(100):
        a = random.randint(0, 200)
        b = random.randint(a, 255)
        got = sorted(x for k, i in dyadic_cover(a, b, 9) for x in range(i << k, (i + 1) << k))
        assert got == list(range(a, b + 1))


def test_cost_model_and_speedup():
    from rowfold.plans.costs import fit_cost_model, speedup

    runs = [(n, d, p, 0.3 + 1e-9 * d**3 + 2e-10 * n * d * d / p) for n in (10**5, 10**6) for d in (10, 80, 320) for p in (2, 8)]
    m = fit_cost_model(runs)
    assert m["per_row"] == pytest.approx(2e-10, rel=1e-3) and m["r2"] > 0.999
    assert speedup({1: 8.0, 4: 2.5})[4] == {"speedup": 3.2, "efficiency": 0.8}


def test_gain_ratio_by_hand():
    ratio, gain = _score([{"a": 4}, {"b": 4}], "gainratio")
    assert ratio == pytest.approx(1) and gain == pytest.approx(1)


def test_errors_name_the_fault(spark):
    df = spark.createDataFrame([(1, "a")], "n int, s string")
    with pytest.raises(validate.InputError) as e:
        ols(df, "n", "x")
    assert e.value.code == "UNKNOWN_COLUMN"
    with pytest.raises(validate.InputError):
        validate.numeric(df, "s")
    assert validate.quoted("a`b") == "`a``b`"


def test_viterbi_of_many_chains_at_once():
    rng = np.random.default_rng(6)
    t = rng.integers(-3, 4, (3, 3)).astype(float)
    chain = [rng.integers(-3, 4, (n, 3)).astype(float) for n in (4, 1, 9, 2, 2, 30, 1)]
    score, path = chains.viterbi_batch(np.concatenate(chain), np.array([len(c) for c in chain]), t)
    for c, s, p in zip(chain, score, np.split(path, np.cumsum([len(c) for c in chain])[:-1])):
        best, way = chains.viterbi_numpy(c, t)
        assert s == best and p.tolist() == way


def test_viterbi_rows_without_tokens_and_long_ones(spark):
    rows = [(1, [[1.0, 0.0]] * 50), (2, []), (3, None), (4, [[0.0, 2.0]])]
    got = {r["doc_id"]: r["score"] for r in chains.viterbi_kernel(spark.createDataFrame(rows, "doc_id long, e array<array<double>>"), np.zeros((2, 2)), most=8).collect()}
    assert got == {1: 50.0, 4: 2.0}


def test_windows_of_words_against_all_windows():
    from rowfold.operators.textops import _window_best

    rng = random.Random(3)
    words = ["ab", "abc", "b", "cab", "bca", "aaa"]
    for _ in range(100):
        text, query = ([rng.choice(words) for _ in range(n)] for n in (rng.randint(0, 12), 3))
        grams = lambda s: {s[i : i + 3] for i in range(len(s) - 2)}
        q = grams(" ".join(query))
        windows = [" ".join(text[i : i + min(k, len(text))]) for k in (2, 3, 4) for i in range(max(1, len(text) - k + 1)) if text]
        sims = [len(grams(w) & q) / len(grams(w) | q) for w in windows if len(grams(w) & q) >= 2]
        assert _window_best("  ".join(text), frozenset(q), 3, (2, 3, 4), 2) == pytest.approx(max(sims, default=0.0))


def test_feature_vectors_and_guards(spark):
    from rowfold.functions import features

    df = spark.createDataFrame([("a", 1.0, [1.0, 2.0]), ("b", 3.0, [float("nan"), 0.0]), (None, None, None), ("c", float("inf"), [1.0, None])], "s string, v double, x array<double>")
    hot = features.one_hot("s", features.categories(df, "s"))
    assert [r[0] for r in df.select(features.assemble(hot, features.number("v"), intercept=True)).collect()][:2] == [[1, 1, 0, 0, 1], [1, 0, 1, 0, 3]]
    assert df.select(features.interaction(hot, features.number("v"))).first()[0] == [1, 0, 0]
    kept, bad = features.guarded(df, ["x"], ["v"])
    assert kept.count() == 1 and bad == {"x": 3, "v": 2}
    with pytest.raises(validate.InputError) as e:
        features.guarded(df, ["x"], policy="error")
    assert e.value.code == "NOT_FINITE"
    with pytest.raises(validate.InputError):
        features.categories(df, "s", 2)
    flat = spark.createDataFrame([(2.0,), (2.0,)], "v double")
    assert [r[0] for r in features.standardise(flat, ["v"]).collect()] == [0, 0]


def test_functions_by_name(spark):
    from rowfold.core import bridge

    df = spark.createDataFrame([([1.0, 2.0], [3.0, 4.0])], "x array<double>, y array<double>")
    assert df.select(bridge.apply_named("dot", "x", "y")).first()[0] == 11
    with pytest.raises(validate.InputError) as e:
        bridge.lookup("nothing")
    assert e.value.code == "UNKNOWN_CALLBACK"


def test_row_orders_and_ids(spark):
    from rowfold.operators.kmeans import kmeans

    df = spark.createDataFrame([(f"id{i}", [float(i % 4), float(i // 4)]) for i in range(12)], "k string, x array<double>")
    for d in ("l1", "sqeuclid"):
        a, b = (kmeans(df, "x", 2, "k", how, init=np.array([[0.0, 0.0], [3.0, 2.0]]), max_iter=3, min_frac_reassigned=-1, distance=d) for how in ("implicit", "fused"))
        assert np.allclose(a.state, b.state) and [r["objective"] for r in a.log.rows] == pytest.approx([r["objective"] for r in b.log.rows])
    with pytest.raises(validate.InputError):
        convex.fit(convex.LeastSquares(2), df.withColumn("y", df["x"][0]), shuffle="sometimes")


def test_topics_keep_every_token_and_treat_repeated_ids_as_one_document(spark):
    """Runs of letters end at a row's end; rows that share an id are one document; both samplers keep all counts."""
    from rowfold.operators.textops import document_terms
    from rowfold.operators.unsupervised import lda, lda_predict

    rows = [(1, "sun moon sun"), (1, "Sun rain"), (2, "rainé9moon"), (3, None), (4, ""), (5, "stone " * 30 + "sun"), (6, "99")]
    t = document_terms(spark.createDataFrame(rows, "doc_id long, text string").coalesce(1), "doc_id", "text").persist()
    got = {r["doc_id"]: dict(zip(r["terms"], r["counts"])) for r in t.collect() if r["terms"]}
    assert got == {1: {"sun": 3, "moon": 1, "rain": 1}, 2: {"rain": 1, "moon": 1}, 5: {"stone": 30, "sun": 1}}
    whole = document_terms(spark.createDataFrame([(1, "ab"), (2, "cd")], "doc_id long, text string").coalesce(1), "doc_id", "text")
    assert sorted(x for r in whole.collect() for x in r["terms"]) == ["ab", "cd"]
    for method in ("gibbs", "vb"):
        f = lda(t, 2, iters=3, method=method)
        assert {r["term"]: round(r["s"], 6) for r in f.frame.groupBy("term").agg({"n": "sum"}).toDF("term", "s").collect()} == {"sun": 4, "moon": 2, "rain": 2, "stone": 30}
        assert {r["doc_id"]: round(r["s"], 6) for r in f.state.groupBy("doc_id").agg({"n": "sum"}).toDF("doc_id", "s").collect()} == {1: 5, 2: 2, 5: 31}
        few = lda(t, 2, iters=1, method=method, least_docs=3)
        assert few.frame.isEmpty()
    long = spark.createDataFrame([(7, "sun", 2), (8, "other", 1)], "doc_id long, term string, cnt long")
    p = lda_predict(long, f.frame, 2).collect()
    assert {r["doc_id"] for r in p} == {7} and abs(sum(r["share"] for r in p) - 1) < 1e-9
    t.unpersist()


def test_cached_and_new_orders_have_as_many_chains(spark):
    """One order for all epochs (cached) and a new one for each are dealt over equally many chains."""
    import numpy as np

    from rowfold.operators import convex

    seen = []
    run = convex.run_fold
    rng = np.random.default_rng(1)
    df = spark.createDataFrame([([1.0, float(v)], float(v > 0)) for v in rng.normal(size=200)], "x array<double>, y double")

    def counted(rows, *a, **kw):
        parts = rows.select(F.spark_partition_id().alias("p")).distinct().count()
        seen.append(parts)
        return run(rows, *a, **kw)

    convex.run_fold = counted
    try:
        for order in ("once", "epoch"):
            convex.fit(convex.Logistic(2, 1e-4), df, "igd", "average", max_iter=1, tol=0.0, shuffle=order)
    finally:
        convex.run_fold = run
    assert seen[0] == seen[1] == int(spark.conf.get("spark.sql.shuffle.partitions"))


def test_range_counts_stay_near_with_many_values(spark, tmp_path):
    """A sketch of a fixed width would add the error of 60,000 values to a range of one."""
    from rowfold.queries import all_queries

    spark.range(300_000).select((F.col("id") % 60_000).alias("user_id")).write.parquet(f"{tmp_path}/events.parquet")
    got = all_queries()["cm_range"](spark, str(tmp_path)).collect()
    assert len(got) == 4 and all(r["never_below"] and r["near"] for r in got)


def test_marginals_and_samples_of_many_chains_at_once():
    rng = np.random.default_rng(3)
    size = np.array([1, 5, 2, 90, 1, 30])
    e, t = rng.normal(size=(size.sum(), 3)) * 2, rng.normal(size=(3, 3))
    begin = np.cumsum(size) - size
    start = np.zeros(len(e), bool)
    start[begin] = True
    z, p, pairs = chains.marginals_batch(e, start, t)
    own = [chains.marginals(e[a : a + n], t) for a, n in zip(begin, size)]
    assert abs(z - sum(x[0] for x in own)) < 1e-9
    assert np.abs(p - np.concatenate([x[1] for x in own])).max() < 1e-9
    assert np.abs(pairs - sum(x[2] for x in own)).max() < 1e-9
    n = chains.gibbs_batch(e, size, list(range(6)), t, 2000, 100)
    assert np.abs(n / 1900 - p).mean() < 0.02
    alone = chains.gibbs_batch(e[8:98], size[3:4], [3], t, 50, 10)
    assert (chains.gibbs_batch(e, size, list(range(6)), t, 50, 10)[8:98] == alone).all()  # a document's own draws


def test_words_of_packed_documents():
    rows = pa.RecordBatch.from_arrays([pa.array([1, 2, 3, 4, 5]), pa.array(["Hello wörld 12", "", None, "a\n\tb  Hello", " "])], names=["id", "text"])
    ((ids, size, word, words),) = textops.word_blocks([rows])
    assert ids.to_pylist() == [1, 4] and size.tolist() == [3, 3]
    assert words.take(pa.array(word)).to_pylist() == ["Hello", "wörld", "12", "a", "b", "Hello"]
    small = list(textops.word_blocks([rows], 1))
    assert [w for b in small for w in b[3].take(pa.array(b[2])).to_pylist()] == ["Hello", "wörld", "12", "a", "b", "Hello"]
    f = chains.word_features(pa.array(["Haus", "HAUS", "maus", "x11", "x99", "ÉCOLE", "école"]), 1 << 20)
    assert f[0, 0] == f[1, 0] and f[0, 1] != f[1, 1] and f[0, 2] == f[2, 2] and f[0, 0] != f[2, 0]
    assert (f[3] == f[4]).all() and f[5, 0] == f[6, 0]


def test_tagger_takes_every_document_with_rows_of_one_id_apart(spark):
    texts = [(i % 40, f"call +49123456{i:03d} or mail a{i}@b.org now " + "plain words " * (i % 7)) for i in range(120)] + [(7, None), (8, " ")]
    labels = ("O", *tasks.ENTITIES)
    blocks = tasks.tag_blocks(spark.createDataFrame(texts, "k int, t string"), "k", "t", tasks.entity_rules, labels, 256)
    m = tasks.train_tagger(blocks, labels, 256, 3)
    assert m.log.rows[-1]["loss"] < m.log.rows[0]["loss"]
    for method in ("viterbi", "mcmc"):
        got = tasks.apply_tagger(blocks, m.state, method)
        assert sorted(len(r["path"]) for r in got.collect()) == sorted(6 + 2 * (i % 7) for i in range(120))
        spans = chains.label_spans(got, labels)
        truth = spans.filter("not found").collect()
        assert sorted((r["start"], r["end"], r["kind"]) for r in truth) == [(1, 1, "LONGNUM")] * 120 + [(4, 4, "EMAIL")] * 120
        hits = {(r["doc_id"], r["start"], r["kind"]) for r in spans.filter("found").collect()} & {(r["doc_id"], r["start"], r["kind"]) for r in truth}
        assert len(hits) > 60


def test_packed_documents_are_dealt_only_where_partitions_are_few(spark):
    words = pa.array(["Haus", "x11", "école", "a", "B2b", "haus", "..", "10,5"])
    assert (chains.word_features(words, 1 << 16, 3) == chains.word_features(words, 1 << 16)).all()
    d = spark.createDataFrame([(i, f"Word {i} the x{i}") for i in range(64)], "k int, t string")
    seen = []
    for parts in (1, 8):
        b = tasks.tag_blocks(d.coalesce(1) if parts == 1 else d.repartition(8), "k", "t", tasks.pos_tag_rules, tasks.POS, 256)
        m = tasks.train_tagger(b, tasks.POS, 256, 2)
        seen.append(sorted((r["doc_id"], tuple(r["label"])) for r in tasks.apply_tagger(b, m.state).collect()))
        assert "words" not in b.columns
    assert seen[0] == seen[1] and len(seen[0]) == 64
