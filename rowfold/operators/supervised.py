"""Naive Bayes, decision trees and support vector machines."""

from __future__ import annotations

import math
from collections.abc import Sequence
from functools import reduce

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rowfold.core import validate
from rowfold.core.driver import FitResult
from rowfold.operators.convex import InsensitiveRegression, LinearSvm, Novelty, Step, fit

# --- naive Bayes -----------------------------------------------------------------------------------------------------


def naive_bayes_fit(df: DataFrame, cls: str, attrs: Sequence[str], smoothing: float = 1.0) -> tuple[DataFrame, DataFrame]:
    """(priors (class, n, logp), conditionals (class, attr, value, n, logp)); values a class never shows are filled in, so
    every (class, attr, value) has a row. One pass over attribute rows."""
    validate.columns(df, cls, *attrs)
    src = df.filter(F.col(cls).isNotNull())
    n = src.groupBy(F.col(cls).alias("class")).agg(F.count("*").alias("n"))
    total = n.agg(F.sum("n").alias("all"))
    priors = n.join(F.broadcast(total)).select("class", "n", F.log(F.col("n") / F.col("all")).alias("logp"))
    pairs = F.explode(F.array(*[F.struct(F.lit(a).alias("attr"), F.col(a).cast("string").alias("value")) for a in attrs]))
    seen = src.select(F.col(cls).alias("class"), pairs.alias("p")).filter("p.value is not null").groupBy("class", "p.attr", "p.value").agg(F.count("*").alias("n"))
    values = seen.groupBy("attr").agg(F.collect_set("value").alias("vs"))
    grid = n.select("class", F.col("n").alias("nc")).join(F.broadcast(values.select("attr", F.size("vs").alias("k"), F.explode("vs").alias("value"))))
    full = grid.join(seen, ["class", "attr", "value"], "left").withColumn("n", F.coalesce("n", F.lit(0)))
    return priors, full.select("class", "attr", "value", "n", F.log((F.col("n") + smoothing) / (F.col("nc") + smoothing * F.col("k"))).alias("logp"))


def gaussian_fit(df: DataFrame, cls: str, attrs: Sequence[str], floor: float = 1e-9) -> DataFrame:
    """(class, n, attr, mean, var) of numeric attributes; variances are floored."""
    agg = df.groupBy(F.col(cls).alias("class")).agg(F.count("*").alias("n"), *[f(F.col(a).cast("double")).alias(f"{k}_{a}") for a in attrs for k, f in (("m", F.avg), ("v", F.var_samp))])
    rows = F.explode(F.array(*[F.struct(F.lit(a).alias("attr"), F.col(f"m_{a}").alias("mean"), F.greatest(F.coalesce(F.col(f"v_{a}"), F.lit(0.0)), F.lit(floor)).alias("var")) for a in attrs]))
    return agg.select("class", "n", rows.alias("r")).select("class", "n", "r.*")


def naive_bayes_text(tokens: DataFrame, cls: str, smoothing: float = 1.0) -> tuple[DataFrame, DataFrame]:
    """Multinomial model of tokens (doc_id, token, class): priors over documents, and (class, token, n, logp). A token
    that a class lacks is scored by the class's own default, which stands in the row with token null."""
    docs = tokens.select("doc_id", F.col(cls).alias("class")).distinct().groupBy("class").agg(F.count("*").alias("n"))
    priors = docs.join(F.broadcast(docs.agg(F.sum("n").alias("all")))).select("class", "n", F.log(F.col("n") / F.col("all")).alias("logp"))
    counts = tokens.groupBy(F.col(cls).alias("class"), "token").agg(F.count("*").alias("n"))
    vocab = tokens.agg(F.countDistinct("token").alias("v"))
    totals = counts.groupBy("class").agg(F.sum("n").alias("t")).join(F.broadcast(vocab))
    model = counts.join(F.broadcast(totals), "class").select("class", "token", "n", F.log((F.col("n") + smoothing) / (F.col("t") + smoothing * F.col("v"))).alias("logp"))
    rest = totals.select("class", F.lit(None).cast("string").alias("token"), F.lit(0).cast("long").alias("n"), F.log(smoothing / (F.col("t") + smoothing * F.col("v"))).alias("logp"))
    return priors, model.unionByName(rest)


def naive_bayes_predict(rows: DataFrame, key: str, pairs: DataFrame, priors: DataFrame, cond: DataFrame) -> DataFrame:
    """(key, class, score, rank): log scores of all classes. pairs: (key, attr, value); a value unknown to the model adds
    nothing. Classes are few; the model is joined on (attr, value)."""
    hit = pairs.join(cond.select("attr", "value", "class", F.col("logp").alias("lp")), ["attr", "value"]).groupBy(key, "class").agg(F.sum("lp").alias("s"))
    every = rows.select(key).join(F.broadcast(priors.select("class", "logp")))
    from pyspark.sql import Window

    scored = every.join(hit, [key, "class"], "left").select(key, "class", (F.col("logp") + F.coalesce("s", F.lit(0.0))).alias("score"))
    return scored.withColumn("rank", F.row_number().over(Window.partitionBy(key).orderBy(F.desc(F.round("score", 9)), "class")))


# --- decision trees --------------------------------------------------------------------------------------------------


def entropy_sum(n: Column) -> Column:
    return F.when(n > 0, n * F.log2(n)).otherwise(0.0)


def split_scores(counts: DataFrame, criterion: str = "gainratio") -> DataFrame:
    """(node, attr, gain, split_info, score) from (node, attr, value, cls, n): multi-way splits by value.

    With N, N_v, N_c and N_vc: gain = sum over v, c of N_vc log N_vc terms; everything comes from grouped sums."""
    vc = counts.groupBy("node", "attr", "value", "cls").agg(F.sum("n").alias("n"))
    v = vc.groupBy("node", "attr", "value").agg(F.sum("n").alias("nv"), F.sum(entropy_sum(F.col("n"))).alias("e"), F.sum(F.col("n") * F.col("n")).alias("q"))
    c = vc.groupBy("node", "attr", "cls").agg(F.sum("n").alias("nc")).groupBy("node", "attr").agg(F.sum("nc").alias("N"), F.sum(entropy_sum(F.col("nc"))).alias("ec"), F.sum(F.col("nc") * F.col("nc")).alias("qc"))
    a = v.groupBy("node", "attr").agg(F.sum(entropy_sum(F.col("nv")) - F.col("e")).alias("within"), F.sum(entropy_sum(F.col("nv"))).alias("ev"), F.sum(F.col("q") / F.col("nv")).alias("gw"))
    j = c.join(a, ["node", "attr"])
    before = F.log2("N") - F.col("ec") / F.col("N")
    gain = F.when(F.lit(criterion == "gini"), F.col("gw") / F.col("N") - F.col("qc") / (F.col("N") * F.col("N"))).otherwise(before - F.col("within") / F.col("N"))
    info = F.log2("N") - F.col("ev") / F.col("N")
    score = F.when(info > 1e-12, gain / info).otherwise(0.0) if criterion == "gainratio" else gain
    return j.select("node", "attr", F.col("N").alias("n"), gain.alias("gain"), info.alias("split_info"), score.alias("score"))


def cut_points(df: DataFrame, attrs: Sequence[str], bins: int) -> dict[str, list[float]]:
    """Candidate thresholds of numeric attributes: distinct approximate quantiles, a bounded number of each."""
    if not attrs:
        return {}
    r = df.agg(*[F.percentile_approx(F.col(a).cast("double"), [i / bins for i in range(1, bins)], 10000).alias(a) for a in attrs]).first()
    return {a: sorted(set(r[a] or [])) for a in attrs}


def tree_fit(
    df: DataFrame, cls: str, cat: Sequence[str] = (), num: Sequence[str] = (), criterion: str = "gainratio", max_depth: int = 5, min_split: int = 2, bins: int = 32,
    missing: str = "ignore", prune: str = "none", cf: float = 0.25, holdout: DataFrame | None = None,
) -> list[dict]:
    """A tree as a list of nodes. One pass per level counts (node, attribute, value, class); the table of counts is of the
    size of the level's nodes times attributes times bins, and the splits are chosen on it.

    missing: ignore (rows without the value do not count for the attribute, and stop at the node) or fraction (they go
    to all branches, weighted by the branches' shares). prune: none, ebp (pessimistic, at confidence cf) or rep (on holdout).
    """
    validate.columns(df, cls, *cat, *num)
    cuts = cut_points(df, num, bins)
    base = df.select(F.col(cls).cast("string").alias("cls"), *[F.col(a).cast("string").alias(a) for a in cat], *[F.col(a).cast("double").alias(a) for a in num]).filter("cls is not null").persist()
    top = {r["cls"]: r["n"] for r in base.groupBy("cls").agg(F.count("*").alias("n")).collect()}
    nodes = [{"id": 0, "parent": None, "depth": 0, "attr": None, "kind": None, "threshold": None, "branch": None, "counts": {k: float(v) for k, v in top.items()}, "children": {}}]
    live = [0]
    for depth in range(max_depth):
        live = [i for i in live if sum(nodes[i]["counts"].values()) >= min_split and sum(v > 0 for v in nodes[i]["counts"].values()) > 1]
        if not live:
            break
        at = assign(base, nodes, missing).filter(F.col("node").isin(live))
        pieces = []
        for a in cat:
            pieces.append(F.struct(F.lit(a).alias("attr"), F.col(a).alias("value")))
        for a in num:  # the bin of the value: it lies at or below cut b and above cut b - 1
            b = F.when(F.col(a).isNull(), None).otherwise(reduce(lambda s, c: s + (F.col(a) > c).cast("int"), cuts[a], F.lit(0)))
            pieces.append(F.struct(F.lit(a).alias("attr"), b.cast("string").alias("value")))
        counts = at.select("node", "w", "cls", F.explode(F.array(*pieces)).alias("p")).groupBy("node", "p.attr", "p.value", "cls").agg(F.sum("w").alias("n")).collect()
        table: dict[tuple, dict] = {}
        for r in counts:
            if r["value"] is not None:
                table.setdefault((r["node"], r["attr"]), {}).setdefault(r["value"], {})[r["cls"]] = r["n"]
        new = []
        for i in live:
            options = []
            for a in [*cat, *num]:
                values = table.get((i, a), {})
                if a in cuts:
                    options += _numeric_splits(a, values, cuts[a], criterion)
                elif len(values) > 1:
                    options.append((*_score(list(values.values()), criterion), a, None, values))
            options = [o for o in options if o[1] > 1e-12]
            if not options:
                continue
            mean = sum(o[1] for o in options) / len(options)
            best = max((o for o in options if o[1] >= mean - 1e-12), key=lambda o: (round(o[0], 12), o[2], -(o[3] or 0)))
            _, _, a, threshold, branches = best
            nodes[i].update(attr=a, kind="num" if threshold is not None else "cat", threshold=threshold)
            for value in sorted(branches):
                k = len(nodes)
                nodes[i]["children"][value] = k
                nodes.append({"id": k, "parent": i, "depth": depth + 1, "attr": None, "kind": None, "threshold": None, "branch": value, "counts": {c: float(n) for c, n in branches[value].items()}, "children": {}})
                new.append(k)
        live = new
    base.unpersist()
    if prune == "ebp":
        _prune_pessimistic(nodes, 0, cf)
    elif prune == "rep" and holdout is not None:
        _prune_reduced(nodes, holdout, cls, cat, num)
    return nodes


def _impurity(counts: dict, criterion: str) -> float:
    n = sum(counts.values())
    if not n:
        return 0.0
    if criterion == "gini":
        return 1 - sum((v / n) ** 2 for v in counts.values())
    return -sum(v / n * math.log2(v / n) for v in counts.values() if v > 0)


def _score(branches: list[dict], criterion: str, cuts: int = 0) -> tuple[float, float]:
    total: dict = {}
    for b in branches:
        for k, v in b.items():
            total[k] = total.get(k, 0) + v
    n = sum(total.values())
    sizes = [sum(b.values()) for b in branches]
    gain = _impurity(total, criterion) - sum(s / n * _impurity(b, criterion) for s, b in zip(sizes, branches))
    if cuts and criterion == "gainratio":
        gain -= math.log2(cuts) / n
    if criterion != "gainratio":
        return gain, gain
    info = -sum(s / n * math.log2(s / n) for s in sizes if s > 0)
    return (gain / info if info > 1e-12 else 0.0), gain


def _numeric_splits(a: str, values: dict, cuts: list[float], criterion: str) -> list[tuple]:
    binned = {int(k): v for k, v in values.items()}
    used = sorted(binned)
    low: dict = {}
    out = []
    for x, nxt in zip(used, used[1:]):
        for k, v in binned[x].items():
            low[k] = low.get(k, 0) + v
        high: dict = {}
        for b in used:
            if b > x:
                for k, v in binned[b].items():
                    high[k] = high.get(k, 0) + v
        out.append((*_score([low, high], criterion, len(used) - 1), a, cuts[x], {"<=": dict(low), ">": high}))
    return out


def _leaf_class(node: dict) -> str:
    return max(sorted(node["counts"]), key=lambda k: node["counts"][k])


def assign(df: DataFrame, nodes: list[dict], missing: str = "ignore") -> DataFrame:
    """df with the node each row reaches and its weight there. The tree becomes one expression; with fractional weights a
    row may reach several nodes."""

    def paths(i: int, weight: Column) -> list[tuple[Column, Column, int]]:
        n = nodes[i]
        if not n["children"]:
            return [(F.lit(True), weight, i)]
        col = F.col(n["attr"])
        sizes = {v: sum(nodes[k]["counts"].values()) for v, k in n["children"].items()}
        total = sum(sizes.values()) or 1.0
        out = []
        known = F.lit(False)
        for v, k in n["children"].items():
            here = (col <= n["threshold"] if v == "<=" else col > n["threshold"]) if n["kind"] == "num" else col == v
            known = known | F.coalesce(here, F.lit(False))
            for cond, w, leaf in paths(k, weight):
                out.append((F.coalesce(here, F.lit(False)) & cond, w, leaf))
                if missing == "fraction":
                    out.append((col.isNull() & cond, w * (sizes[v] / total), leaf))
        stay = ~known & (col.isNotNull() if missing == "fraction" else F.lit(True))
        return [*out, (stay, weight, i)]

    own = paths(0, F.lit(1.0))
    if missing != "fraction":
        node = reduce(lambda c, p: c.when(p[0], F.lit(p[2])), own[1:], F.when(own[0][0], F.lit(own[0][2])))
        return df.withColumn("node", node).withColumn("w", F.lit(1.0))
    hits = F.filter(F.array(*[F.when(c, F.struct(F.lit(i).alias("node"), w.alias("w"))) for c, w, i in own]), lambda s: s.isNotNull())
    return df.withColumn("__h", F.explode(hits)).withColumn("node", F.col("__h.node")).withColumn("w", F.col("__h.w")).drop("__h")


def tree_predict(df: DataFrame, nodes: list[dict]) -> DataFrame:
    """df with the predicted class: one generated expression, no Python."""
    at = assign(df, nodes)
    label = reduce(lambda c, n: c.when(F.col("node") == n["id"], F.lit(_leaf_class(n))), nodes[1:], F.when(F.col("node") == 0, F.lit(_leaf_class(nodes[0]))))
    return at.withColumn("predicted", label).drop("w")


def tree_rules(nodes: list[dict]) -> list[str]:
    out = []

    def walk(i: int, path: list[str]) -> None:
        n = nodes[i]
        if not n["children"]:
            out.append(f"{' and '.join(path) or 'always'} -> {_leaf_class(n)} {sorted(n['counts'].items())}")
        for v, k in n["children"].items():
            walk(k, [*path, f"{n['attr']} {v} {n['threshold']}" if n["kind"] == "num" else f"{n['attr']} = {v}"])

    walk(0, [])
    return out


def tree_table(spark, nodes: list[dict]) -> DataFrame:
    rows = [(n["id"], n["parent"], n["depth"], n["attr"], n["kind"], float(n["threshold"]) if n["threshold"] is not None else None, n["branch"], _leaf_class(n), float(sum(n["counts"].values())), not n["children"]) for n in nodes]
    return spark.createDataFrame(rows, "node_id int, parent int, depth int, attr string, kind string, threshold double, branch string, class string, n double, leaf boolean")


def _upper(errors: float, n: float, cf: float) -> float:
    """Upper limit of a binomial rate at confidence cf, by bisection on the tail."""
    if n <= 0:
        return 0.0
    if errors < 1e-9:
        return 1 - cf ** (1 / n)
    from rowfold.functions.dist import beta_inc

    low, high = errors / n, 1.0
    for _ in range(60):
        mid = (low + high) / 2
        low, high = (mid, high) if 1 - beta_inc(errors + 1, max(n - errors, 1e-9), mid) > cf else (low, mid)
    return (low + high) / 2


def _prune_pessimistic(nodes: list[dict], i: int, cf: float) -> float:
    n = nodes[i]
    total = sum(n["counts"].values())
    own = total * _upper(total - max(n["counts"].values(), default=0), total, cf)
    if not n["children"]:
        return own
    below = sum(_prune_pessimistic(nodes, k, cf) for k in n["children"].values())
    if own <= below + 0.1:
        n.update(children={}, attr=None, kind=None, threshold=None)
        return own
    return below


def _prune_reduced(nodes: list[dict], holdout: DataFrame, cls: str, cat, num) -> None:
    src = holdout.select(F.col(cls).cast("string").alias("cls"), *cat, *num)
    reached = assign(src, nodes).groupBy("node", "cls").count().collect()
    own: dict[int, dict] = {}
    for r in reached:
        own.setdefault(r["node"], {})[r["cls"]] = r["count"]

    def walk(i: int) -> tuple[dict, float]:
        n = nodes[i]
        counts = dict(own.get(i, {}))
        label = _leaf_class(n)
        wrong = sum(v for k, v in counts.items() if k != label)
        for k in n["children"].values():
            c, w = walk(k)
            wrong += w
            for a, v in c.items():
                counts[a] = counts.get(a, 0) + v
        flat = sum(v for k, v in counts.items() if k != label)
        if n["children"] and flat <= wrong:
            n.update(children={}, attr=None, kind=None, threshold=None)
            wrong = flat
        return counts, wrong

    walk(0)


# --- support vector machines -----------------------------------------------------------------------------------------


def random_features(df: DataFrame, x: str, d_in: int, d_out: int, gamma: float = 1.0, seed: int = 0, out: str = "x") -> DataFrame:
    """Random Fourier features of a Gaussian kernel: a fixed projection in expressions."""
    rng = np.random.default_rng(seed)
    w, b = rng.normal(0, math.sqrt(2 * gamma), (d_out, d_in)), rng.uniform(0, 2 * math.pi, d_out)
    rows = F.array(*[F.struct(F.array(*map(F.lit, map(float, w[i]))).alias("w"), F.lit(float(b[i])).alias("b")) for i in range(d_out)])
    scale = math.sqrt(2 / d_out)
    feats = F.transform(rows, lambda r: F.cos(F.aggregate(F.zip_with(F.col(x).cast("array<double>"), r["w"], lambda p, q: p * q), F.lit(0.0), lambda s, v: s + v) + r["b"]) * scale)
    return df.withColumn(out, feats)


def svm(df: DataFrame, y: str, x: str, task: str = "classify", l2: float = 0.01, eps: float = 0.1, nu: float = 0.1, max_iter: int = 20, solver: str = "igd", mode: str = "average") -> FitResult:
    src = df.select(F.col(x).cast("array<double>").alias("x"), F.col(y).cast("double").alias("y")).dropna()
    d = validate.same_length(src, "x")
    obj = {"classify": lambda: LinearSvm(d, l2), "regress": lambda: InsensitiveRegression(d, eps, l2), "novelty": lambda: Novelty(d, nu)}[task]()
    return fit(obj, src, solver, mode, Step.decay(0.5, 0.5) if solver != "gd" else None, max_iter)
