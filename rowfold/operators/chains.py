"""Linear-chain models: Viterbi in several forms, forward-backward, sampling, training, and an HMM baseline.

A model is a table of emission weights (feature, label, weight) and transition
weights (previous label, label, weight). Scores of a document are packed as one
array of label scores per token; documents are independent, so every method works
on rows of packed documents without a shuffle beyond the packing.
"""

from __future__ import annotations

import heapq
import math
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from rowfold.core.driver import FitResult, IterationLog, stage
from rowfold.core.fold import Fold, run_fold


def label_scores(features: DataFrame, weights: DataFrame, labels: list[str], tokens: DataFrame) -> DataFrame:
    """(doc_id, pos, s): the label scores of every token, 0 where no feature fires."""
    cols = [F.sum(F.when(F.col("label") == l, F.col("weight") * F.col("value")).otherwise(0.0)).alias(f"s{i}") for i, l in enumerate(labels)]
    got = features.join(F.broadcast(weights), "feature").groupBy("doc_id", "pos").agg(*cols)
    s = F.array(*[F.coalesce(F.col(f"s{i}"), F.lit(0.0)) for i in range(len(labels))])
    return tokens.select("doc_id", "pos").join(got, ["doc_id", "pos"], "left").select("doc_id", "pos", s.alias("s"))


def pack(scores: DataFrame) -> DataFrame:
    """(doc_id, e): one array of token score arrays per document, by place."""
    return scores.groupBy("doc_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("pos", "s"))), lambda x: x["s"]).alias("e"))


def transitions_of(trans: dict[tuple[str, str], float], labels: list[str]) -> np.ndarray:
    t = np.zeros((len(labels), len(labels)))
    for (a, b), w in trans.items():
        t[labels.index(a), labels.index(b)] = w
    return t


# --- Viterbi ---------------------------------------------------------------------------------------------------------


def _best_previous(v: Column, trans: np.ndarray, j: int) -> Column:
    """struct(score, place) of the best label before label j; ties to the lesser place."""
    n = len(trans)
    return F.array_max(F.array(*[F.struct((F.get(v, F.lit(k)) + float(trans[k, j])).alias("s"), F.lit(-k).alias("k")) for k in range(n)]))


def viterbi_fold(packed: DataFrame, trans: np.ndarray) -> DataFrame:
    """(doc_id, score, path) by an array fold in expressions: forward with back-pointers, then a fold back over them."""
    n = len(trans)
    first = F.struct(F.get("e", F.lit(0)).alias("v"), F.array().cast("array<array<int>>").alias("back"))

    def step(acc, e):
        best = F.array(*[_best_previous(acc["v"], trans, j) for j in range(n)])
        return F.struct(F.zip_with(best, e, lambda b, x: b["s"] + x).alias("v"), F.concat(acc["back"], F.array(F.transform(best, lambda b: (-b["k"]).cast("int")))).alias("back"))

    run = packed.withColumn("r", F.aggregate(F.slice("e", F.lit(2), F.greatest(F.size("e") - 1, F.lit(0))), first, step))
    top = F.array_max(F.transform(F.col("r.v"), lambda x, i: F.struct(x.alias("s"), (-i).alias("k"))))
    last = (-top["k"]).cast("int")
    path = F.aggregate(F.reverse(F.col("r.back")), F.array(last), lambda acc, b: F.concat(F.array(F.get(b, F.get(acc, F.lit(0)))), acc))
    return run.select("doc_id", top["s"].alias("score"), path.alias("path"))


def viterbi_numpy(e: np.ndarray, trans: np.ndarray) -> tuple[float, list[int]]:
    v, back = e[0].copy(), []
    for x in e[1:]:
        s = v[:, None] + trans
        b = s.argmax(0)
        back.append(b)
        v = s[b, np.arange(len(v))] + x
    k = int(v.argmax())
    path = [k]
    for b in reversed(back):
        path.append(int(b[path[-1]]))
    return float(v.max()), path[::-1]


def viterbi_batch(flat: np.ndarray, size: np.ndarray, trans: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(scores, paths one after another) of many chains, whose token scores lie one after another. All chains advance
    together, the longer ones first, so that those that still run are a slice."""
    n = len(trans)
    begin = np.cumsum(size) - size
    order = np.argsort(-size, kind="stable")
    begin, length = begin[order], size[order]
    longest = int(length[0]) if len(length) else 0
    alive = np.searchsorted(-length, -np.arange(longest), side="left")  # chains with a token at each place
    v = np.zeros((len(size), n))
    back = []
    for t in range(longest):
        own = alive[t]
        x = flat[begin[:own] + t]
        if t:
            s = v[:own, :, None] + trans[None]
            b = s.argmax(1)
            back.append(b.astype(np.int16))
            x = x + np.take_along_axis(s, b[:, None, :], 1)[:, 0]
        v[:own] = x
    label = v.argmax(1)
    path = np.empty(len(flat), np.int32)
    for t in range(longest - 1, -1, -1):
        own = alive[t]
        path[begin[:own] + t] = label[:own]
        if t:
            label[:own] = back[t - 1][np.arange(own), label[:own]]
    score = np.zeros(len(size))
    score[order] = v.max(1)
    return score, path


def viterbi_top(e: np.ndarray, trans: np.ndarray, k: int) -> list[tuple[float, list[int]]]:
    """The k best labelings; ties by the lesser last label, then the better rank before."""
    n = len(trans)
    cells = [[(float(e[0, j]), -1, -1)] for j in range(n)]
    table = [cells]
    for x in e[1:]:
        cells = [heapq.nsmallest(k, ((-(s[0] + trans[i, j] + x[j]), i, r) for i in range(n) for r, s in enumerate(table[-1][i]))) for j in range(n)]
        table.append([[(-a, i, r) for a, i, r in c] for c in cells])
    ends = heapq.nsmallest(k, ((-s[0], j, r) for j in range(n) for r, s in enumerate(table[-1][j])))
    out = []
    for s, j, r in ends:
        path, t = [], len(table) - 1
        while j >= 0:
            path.append(j)
            _, j, r = table[t][j][r]
            t -= 1
        out.append((-s, path[::-1]))
    return out


def _per_document(packed: DataFrame, f, schema: str, names: list[str], kinds: list) -> DataFrame:
    kind = dict(packed.dtypes)["doc_id"]

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            ids, cols = [], [[] for _ in names]
            for d, e in zip(b.column(0), b.column(1).to_pylist()):
                for row in f(d.as_py(), np.array(e, float)):
                    ids.append(d.as_py())
                    for c, v in zip(cols, row):
                        c.append(v)
            yield pa.RecordBatch.from_arrays([pa.array(ids, b.column(0).type), *(pa.array(c, k) for c, k in zip(cols, kinds))], names=["doc_id", *names])

    return packed.select("doc_id", "e").mapInArrow(work, f"doc_id {kind}, {schema}")


def viterbi_kernel(packed: DataFrame, trans: np.ndarray, k: int = 1, most: int = 1 << 20) -> DataFrame:
    """(doc_id, rank, score, path), the k best labelings of each document; one without tokens has none. For k = 1 all
    documents of a batch of up to `most` tokens (or one document) advance together."""
    if k > 1:
        best = lambda _, e: [(r + 1, s, p) for r, (s, p) in enumerate(viterbi_top(e, trans, k))]
        return _per_document(packed, best, "rank int, score double, path array<int>", ["rank", "score", "path"], [pa.int32(), pa.float64(), pa.list_(pa.int32())])
    kind, n = dict(packed.dtypes)["doc_id"], len(trans)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            off = np.asarray(whole.column(1).offsets)
            at = 0
            while at < whole.num_rows:
                to = max(at + 1, int(np.searchsorted(off, off[at] + most, side="right")) - 1)
                b, at = whole.slice(at, min(to, whole.num_rows) - at), to
                b = b.filter(pc.fill_null(pc.greater(pc.list_value_length(b.column(1)), 0), False))
                if not b.num_rows:
                    continue
                size = pc.list_value_length(b.column(1)).to_numpy().astype(np.int64)
                score, path = viterbi_batch(np.asarray(b.column(1).flatten().flatten(), float).reshape(-1, n), size, trans)
                paths = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(size)]).astype(np.int32)), pa.array(path))
                yield pa.RecordBatch.from_arrays([b.column(0), pa.array(np.ones(len(size), np.int32)), pa.array(score), paths], names=["doc_id", "rank", "score", "path"])

    return packed.select("doc_id", "e").mapInArrow(work, f"doc_id {kind}, rank int, score double, path array<int>")


def viterbi_driver(scores: DataFrame, trans: np.ndarray) -> DataFrame:
    """(doc_id, score, path) by one job a position over all documents, as many as the longest has tokens; the state table
    holds each document's label scores and paths and is staged every few rounds."""
    n = len(trans)
    longest = (scores.agg(F.max("pos")).first()[0] or 0) + 1
    state = scores.filter("pos = 0").select("doc_id", F.col("s").alias("v"), F.transform(F.sequence(F.lit(0), F.lit(n - 1)), lambda j: F.array(j)).alias("paths"))
    for p in range(1, longest):
        step = state.join(scores.filter(F.col("pos") == p).select("doc_id", F.col("s").alias("x")), "doc_id", "left")
        best = F.array(*[_best_previous(F.col("v"), trans, j) for j in range(n)])
        moved = step.withColumn("b", best)
        v = F.zip_with("b", "x", lambda b, x: b["s"] + x)
        paths = F.transform("b", lambda b, j: F.concat(F.get(F.col("paths"), (-b["k"]).cast("int")), F.array(j)))
        state = moved.select("doc_id", F.when(F.col("x").isNull(), F.col("v")).otherwise(v).alias("v"), F.when(F.col("x").isNull(), F.col("paths")).otherwise(paths).alias("paths"))
        if p % 8 == 0:
            state = stage(state, "viterbi")
    top = F.array_max(F.transform("v", lambda x, i: F.struct(x.alias("s"), (-i).alias("k"))))
    return state.select("doc_id", top["s"].alias("score"), F.get("paths", (-top["k"]).cast("int")).alias("path"))


def viterbi_recursive(spark: SparkSession, scores: DataFrame, trans: np.ndarray, longest: int) -> DataFrame:
    """(doc_id, score, path) by a recursive query that carries the label scores and paths as arrays. A level is a job."""
    scores.createOrReplaceTempView("rf_chain")
    n = len(trans)
    best = ", ".join("array_max(array(" + ", ".join(f"named_struct('s', r.v[{k}] + {float(trans[k, j])}D, 'k', -{k})" for k in range(n)) + "))" for j in range(n))
    sql = f"""
      WITH RECURSIVE rf_walk(doc_id, pos, v, paths) MAX RECURSION LEVEL {longest + 1} AS (
        SELECT doc_id, pos, s, transform(sequence(0, {n - 1}), j -> array(j)) FROM rf_chain WHERE pos = 0
        UNION ALL
        SELECT doc_id, pos, zip_with(b, x, (p, q) -> p.s + q), transform(b, (p, j) -> concat(old[-p.k], array(j)))
        FROM (SELECT r.doc_id, c.pos, array({best}) AS b, c.s AS x, r.paths AS old FROM rf_walk r JOIN rf_chain c ON c.doc_id = r.doc_id AND c.pos = r.pos + 1))
      SELECT * FROM rf_walk"""
    walk = spark.sql(sql)
    last = walk.groupBy("doc_id").agg(F.max_by(F.struct("v", "paths"), "pos").alias("z"))
    top = F.array_max(F.transform(F.col("z.v"), lambda x, i: F.struct(x.alias("s"), (-i).alias("k"))))
    return last.select("doc_id", top["s"].alias("score"), F.get(F.col("z.paths"), (-top["k"]).cast("int")).alias("path"))


def viterbi_window(scores: DataFrame, trans: np.ndarray) -> DataFrame:
    """(doc_id, score, path) by a window over each document's tokens: the frame up to a token is folded to its label scores,
    and the last frame gives the path. A frame is folded anew for every token, so this form is quadratic in a document."""
    n = len(trans)
    w = Window.partitionBy("doc_id").orderBy("pos")
    so_far = F.collect_list("s").over(w.rowsBetween(Window.unboundedPreceding, Window.currentRow))
    framed = scores.withColumn("e", so_far).withColumn("last", F.max("pos").over(Window.partitionBy("doc_id"))).filter("pos = last").select("doc_id", "e")
    return viterbi_fold(framed, trans)


# --- likelihood ------------------------------------------------------------------------------------------------------


def log_likelihood(scores: DataFrame, trans: np.ndarray) -> DataFrame:
    """(doc_id, score, log_z, loglik) of given labelings: scores has (doc_id, pos, s, label), label a place in s. What a
    labeling's labels and neighbours add up to, less the log of the sum over all labelings."""
    w = F.array(*[F.array(*map(F.lit, map(float, row))) for row in trans])
    prev = F.lag("label").over(Window.partitionBy("doc_id").orderBy("pos"))
    own = scores.withColumn("prev", prev).groupBy("doc_id").agg(F.sum(F.get("s", F.col("label")) + F.coalesce(F.get(F.get(w, F.col("prev")), F.col("label")), F.lit(0.0))).alias("score"))
    z = forward_backward(pack(scores.select("doc_id", "pos", "s")), trans).filter("pos = 0 and label = 0").select("doc_id", "log_z")
    return own.join(z, "doc_id").withColumn("loglik", F.col("score") - F.col("log_z"))


# --- exact marginals and sampling ------------------------------------------------------------------------------------


def _lse(x: np.ndarray, axis: int) -> np.ndarray:
    m = x.max(axis=axis, keepdims=True)
    return (m + np.log(np.exp(x - m).sum(axis=axis, keepdims=True))).squeeze(axis)


def marginals(e: np.ndarray, trans: np.ndarray) -> tuple[float, np.ndarray, np.ndarray]:
    """(log Z, token marginals, summed pair marginals)."""
    a = [e[0]]
    for x in e[1:]:
        a.append(_lse(a[-1][:, None] + trans, 0) + x)
    b = [np.zeros(e.shape[1])]
    for x in e[:0:-1]:
        b.append(_lse(trans + (x + b[-1])[None, :], 1))
    b = b[::-1]
    z = float(_lse(a[-1], 0))
    p = np.exp(np.array(a) + np.array(b) - z)
    pairs = np.zeros_like(trans)
    for t in range(1, len(e)):
        pairs += np.exp(a[t - 1][:, None] + trans + (e[t] + b[t])[None, :] - z)
    return z, p, pairs


def forward_backward(packed: DataFrame, trans: np.ndarray) -> DataFrame:
    """(doc_id, pos, label, p, log_z)."""

    def rows(_, e):
        z, p, _ = marginals(e, trans)
        return [(t, j, float(p[t, j]), z) for t in range(len(e)) for j in range(e.shape[1])]

    return _per_document(packed, rows, "pos int, label int, p double, log_z double", ["pos", "label", "p", "log_z"], [pa.int32(), pa.int32(), pa.float64(), pa.float64()])


def gibbs_chain(e: np.ndarray, trans: np.ndarray, n_iter: int, burn_in: int, thin: int, rng) -> np.ndarray:
    """Label counts by token after the burn-in: each sweep draws every label from its conditional."""
    t, n = e.shape
    y = e.argmax(1)
    counts = np.zeros((t, n))
    for it in range(n_iter):
        u = rng.random(t)
        for i in range(t):
            s = e[i] + (trans[y[i - 1]] if i else 0) + (trans[:, y[i + 1]] if i + 1 < t else 0)
            p = np.exp(s - s.max())
            y[i] = min(n - 1, int(np.searchsorted(np.cumsum(p), u[i] * p.sum())))
        if it >= burn_in and (it - burn_in) % thin == 0:
            counts[np.arange(t), y] += 1
    return counts


def mh_chain(e: np.ndarray, trans: np.ndarray, n_iter: int, burn_in: int, thin: int, rng) -> tuple[np.ndarray, float]:
    """The same by proposals of one random label at one random token, and the share accepted."""
    t, n = e.shape
    y = e.argmax(1)
    counts, taken = np.zeros((t, n)), 0
    for it in range(n_iter * t):
        i, l, u = int(rng.integers(t)), int(rng.integers(n)), rng.random()
        d = e[i, l] - e[i, y[i]]
        if i:
            d += trans[y[i - 1], l] - trans[y[i - 1], y[i]]
        if i + 1 < t:
            d += trans[l, y[i + 1]] - trans[y[i], y[i + 1]]
        if math.log(max(u, 1e-300)) < d:
            taken += y[i] != l
            y[i] = l
        if it >= burn_in * t and (it - burn_in * t) % (thin * t) == 0:
            counts[np.arange(t), y] += 1
    return counts, taken / max(1, n_iter * t)


def mcmc(packed: DataFrame, trans: np.ndarray, sampler: str = "gibbs", n_iter: int = 200, burn_in: int = 50, thin: int = 1, chains: int = 1, seed: int = 0) -> DataFrame:
    """(doc_id, pos, label, p, r_hat): estimated marginals over all chains, and how far the chains are apart. Chains of one
    document are folds of their own; randomness follows from seed, document and chain."""

    def rows(d, e):
        per = []
        for c in range(chains):
            rng = np.random.default_rng([seed, abs(hash(str(d))) % (1 << 31) if not isinstance(d, int) else d % (1 << 31), c])
            got = gibbs_chain(e, trans, n_iter, burn_in, thin, rng) if sampler == "gibbs" else mh_chain(e, trans, n_iter, burn_in, thin, rng)[0]
            per.append(got)
        n = per[0][0].sum()
        p = sum(per) / (n * chains)
        share = np.array(per) / n
        within = (share * (1 - share)).mean(0)
        r = np.sqrt(1 + share.var(0, ddof=1) / np.maximum(within, 1e-12)) if chains > 1 else np.full(p.shape, np.nan)
        return [(t, j, float(p[t, j]), float(r[t, j])) for t in range(len(e)) for j in range(e.shape[1])]

    return _per_document(packed, rows, "pos int, label int, p double, r_hat double", ["pos", "label", "p", "r_hat"], [pa.int32(), pa.int32(), pa.float64(), pa.float64()])


def mcmc_driver(packed: DataFrame, trans: np.ndarray, n_iter: int = 20, burn_in: int = 5, seed: int = 0) -> DataFrame:
    """Gibbs sampling coordinated by the driver: one sweep over all documents a round, with the labels as a staged table.
    The same draws as one chain per document would make, at the cost of a job a round."""
    state = stage(packed.withColumn("y", F.transform("e", lambda x: (F.array_position(x, F.array_max(x)) - 1).cast("int"))), "mcmc")
    kind = dict(packed.dtypes)["doc_id"]
    kept = []
    for it in range(n_iter):

        def sweep(batches: Iterator[pa.RecordBatch], it=it) -> Iterator[pa.RecordBatch]:
            for b in batches:
                ys = []
                for d, e, y in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2).to_pylist()):
                    e, rng = np.array(e, float), np.random.default_rng([seed, d % (1 << 31), it])
                    t, n = e.shape
                    u = rng.random(t)
                    for i in range(t):
                        s = e[i] + (trans[y[i - 1]] if i else 0) + (trans[:, y[i + 1]] if i + 1 < t else 0)
                        p = np.exp(s - s.max())
                        y[i] = min(n - 1, int(np.searchsorted(np.cumsum(p), u[i] * p.sum())))
                    ys.append(y)
                yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(ys, pa.list_(pa.int32()))], names=["doc_id", "e", "y"])

        state = stage(state.mapInArrow(sweep, f"doc_id {kind}, e array<array<double>>, y array<int>"), "mcmc")
        if it >= burn_in:
            kept.append(state.select("doc_id", F.posexplode("y").alias("pos", "label")))
    every = kept[0]
    for k in kept[1:]:
        every = every.unionByName(k)
    return every.groupBy("doc_id", "pos", "label").agg((F.count("*") / F.lit(float(len(kept)))).alias("p"))


# --- training --------------------------------------------------------------------------------------------------------


def marginals_batch(e: np.ndarray, start: np.ndarray, trans: np.ndarray) -> tuple[float, np.ndarray, np.ndarray]:
    """(sum of the chains' log Z, token marginals, summed pair marginals) of chains that lie one after another; start marks
    their first tokens. The sequence is cut into lanes that advance together. What a lane makes of any vector is a matrix;
    these give the vectors at the cuts, so no chain is cut short."""
    size, n = e.shape
    steps = max(1, int((size / 8) ** 0.5))
    lanes = -(-size // steps)
    e = np.ascontiguousarray(e.T)
    top, high = e.max(0), trans.max()
    x = np.zeros((n, lanes * steps))
    x[0] = 1  # tokens that fill the last lane are chains of their own, with Z = 1
    np.exp(e - top, out=x[:, :size])
    new = np.ones(lanes * steps, bool)
    new[:size] = start
    x = np.ascontiguousarray(x.reshape(n, lanes, steps).transpose(2, 0, 1))  # lanes last, as they are many
    new = np.ascontiguousarray(new.reshape(lanes, steps).T)
    firsts = [np.flatnonzero(r) for r in new]
    w = np.exp(trans - high)
    ahead = np.ascontiguousarray(w.T)
    m = np.repeat(np.eye(n)[:, :, None], lanes, 2)
    for t in range(steps):
        q = np.matmul(ahead, m)
        if len(firsts[t]):
            q[:, :, firsts[t]] = m[:, :, firsts[t]].sum(1, keepdims=True)
        q *= x[t]
        if t % 4 == 3 or t == steps - 1:
            q /= q.sum((0, 1))
        m = q
    m = np.ascontiguousarray(m.transpose(2, 0, 1))
    enter, leave = np.full((lanes, n), 1 / n), np.ones((lanes, n))
    for b in range(1, lanes):
        v = enter[b - 1].dot(m[b - 1])
        enter[b] = v / v.sum()
        v = m[-b].dot(leave[-b])
        leave[-b - 1] = v / v.sum()
    a, z, v = np.empty_like(x), np.empty((steps, lanes)), np.ascontiguousarray(enter.T)
    before = np.empty_like(x)
    for t in range(steps):
        u = ahead @ v
        u[:, firsts[t]] = 1
        u *= x[t]
        z[t] = u.sum(0)
        before[t] = v
        v = np.divide(u, z[t], out=a[t])
    b = np.empty_like(x)
    b[-1] = leave.T
    for t in range(steps - 1, 0, -1):
        v = x[t] * b[t]
        u = w @ v
        if len(firsts[t]):
            u[:, firsts[t]] = v[:, firsts[t]].sum(0)
        np.divide(u, u.sum(0), out=b[t - 1])
    p = a * b
    p /= p.sum(1, keepdims=True)
    after = x * b
    both = np.matmul(ahead, before)
    both *= after
    share = np.where(new, 0, 1 / both.sum(1))
    before *= share[:, None]
    pairs = w * np.matmul(before, after.transpose(0, 2, 1)).sum(0)
    return float(np.log(z).sum() + top.sum() + high * (~start).sum()), p.transpose(1, 2, 0).reshape(n, -1)[:, :size].T, pairs


#: Columns of a row of packed documents: ids, tokens of each, word of each token, hashed features of each word, and words.
BLOCK = "size binary, word binary, features binary"
#: Hashed features of a word: itself, its shape, its ending, its digits and length. The place of a token gives one more.
PER_WORD = 4


def _mixed(h: np.ndarray, kind: int) -> np.ndarray:
    h = (h + np.uint64(kind)) * np.uint64(0x9E3779B97F4A7C15)
    h = (h ^ (h >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    h = (h ^ (h >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return h ^ (h >> np.uint64(31))


def place_features(dim: int) -> tuple[int, int]:
    """Features of a document's first token and of the others."""
    first, rest = _mixed(np.arange(2, dtype=np.uint64), PER_WORD) % np.uint64(dim)
    return int(first), int(rest)


def word_features(words: pa.Array, dim: int, most: int = 1 << 14) -> np.ndarray:
    """(words, PER_WORD) features below dim of words without line ends, none of them empty; `most` words at once."""
    if len(words) > most:
        return np.concatenate([word_features(words.slice(a, most), dim, most) for a in range(0, len(words), most)])

    def points(text: str) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Code points of all words, where each begins, and the word of each."""
        c = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32)
        end = c == 10
        word = np.cumsum(end) - end
        return c[~end], np.searchsorted(word[~end], np.arange(len(words))), word[~end]

    def hashed(c: np.ndarray, begin: np.ndarray, word: np.ndarray, kind: int) -> np.ndarray:
        place = np.arange(len(c)) - begin[word]
        power = np.multiply.accumulate(np.full(int(place.max()) + 1, 0x100000001B3, np.uint64))
        return _mixed(np.add.reduceat((c.astype(np.uint64) + np.uint64(1)) * power[place], begin), kind)

    if not len(words):
        return np.zeros((0, PER_WORD), np.int32)
    text = "\n".join(words.to_pylist()) + "\n"
    c, begin, word = points(text.lower())
    digit = (c >= 48) & (c <= 57)
    low = np.where(digit, 48, c)
    ends = np.append(begin[1:], len(c))
    tail = np.arange(len(c)) >= ends[word] - 2
    own = [hashed(low, begin, word, 0)]
    ending = hashed(low[tail], np.searchsorted(word[tail], np.arange(len(words))), word[tail], 2)
    c, begin, word = points(text)
    long = np.diff(np.append(begin, len(c)))
    shape = np.where((c >= 65) & (c <= 90), 88, np.where((c >= 97) & (c <= 122), 120, np.where((c >= 48) & (c <= 57), 100, c)))
    fresh = np.ones(len(c), bool)
    fresh[1:] = (shape[1:] != shape[:-1]) | (word[1:] != word[:-1])
    own.append(hashed(shape[fresh], np.searchsorted(word[fresh], np.arange(len(words))), word[fresh], 1))
    number = np.logical_or.reduceat((c >= 48) & (c <= 57), begin)
    own += [ending, _mixed((number * 5 + np.minimum(long // 4, 4)).astype(np.uint64), 3)]
    return np.stack([(h % np.uint64(dim)).astype(np.int32) for h in own], 1)


def crf_blocks(df: DataFrame, id_col: str, text_col: str, dim: int) -> DataFrame:
    """(docs, BLOCK, words): documents packed by about 4 MB of text, without those that have no token. A block's distinct
    words are listed once, so what follows from a word is computed for each of them and not for each token."""
    from rowfold.operators.textops import word_blocks

    src = df.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text"))
    kind = dict(src.dtypes)["doc_id"]

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for ids, size, word, words in word_blocks(batches):
            cell = lambda x: pa.array([np.ascontiguousarray(x, np.int32).tobytes()], pa.binary())
            lists = [pa.ListArray.from_arrays(pa.array([0, len(c)], pa.int32()), c) for c in (ids, words)]
            yield pa.RecordBatch.from_arrays([lists[0], cell(size), cell(word), cell(word_features(words, dim)), lists[1]], names=["docs", "size", "word", "features", "words"])

    return src.mapInArrow(work, f"docs array<{kind}>, {BLOCK}, words array<string>")


def _unpacked(b: pa.RecordBatch, at: dict[str, int]) -> Iterator[tuple[pa.Array, np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """(ids, tokens of each document, word of each token, features of each word, label of each word) of each block."""
    for i in range(b.num_rows):
        size, word, features = (np.frombuffer(b.column(at[c])[i].as_buffer(), np.int32) for c in ("size", "word", "features"))
        ids = b.column(at["docs"])[i].values if "docs" in at else None
        yield ids, size, word, features.reshape(-1, PER_WORD), np.asarray(b.column(at["label"])[i].values)


def _emissions(features: np.ndarray, first: np.ndarray, em: np.ndarray) -> np.ndarray:
    """Label scores of tokens with these features of their words; first: places of the documents' first tokens."""
    e = em[features[:, 0]]
    for f in range(1, PER_WORD):
        e += em[features[:, f]]
    begin, rest = place_features(len(em))
    e += em[rest]
    e[first] += em[begin] - em[rest]
    return e


class _CrfFold(Fold):
    """A chain of gradient steps over a partition's blocks, each weight with a step that shrinks with its own past
    gradients. A step takes one document at first, later as many as hold a sixteenth of the tokens seen, up to `most` tokens;
    its gradient is scaled by the root of their number. Models are averaged weight by weight over the chains that touched it, so that what
    is rare is not thinned out. The model is dense in hashed features."""

    schema = "n long, w array<double>, g array<double>, loss double"
    columns = ("size", "word", "features", "label")

    def __init__(self, w: np.ndarray, g: np.ndarray, dim: int, labels: int, step: float, l2: float, most: int = 1 << 16):
        self.w, self.g, self.dim, self.labels, self.alpha, self.l2, self.most = w, g, dim, labels, step, l2, most

    def zero(self):
        return None

    def step(self, s, batch):
        s = s or (0, self.w.copy(), self.g.copy(), np.zeros_like(self.w), 0.0)
        for _, size, word, features, label in _unpacked(batch, {c: i for i, c in enumerate(self.columns)}):
            ends = np.cumsum(size)
            a = 0
            while a < len(size):
                begin = int(ends[a] - size[a])
                z = max(a + 1, int(np.searchsorted(ends, begin + min(self.most, s[0] // 16), side="right")))
                own = word[begin : ends[z - 1]]
                s = self._moved(s, features[own], label[own], ends[a:z] - size[a:z] - begin)
                a = z
        return s

    def _moved(self, s, features: np.ndarray, y: np.ndarray, first: np.ndarray):
        n, w, g, touched, loss = s
        k, cut = self.labels, self.dim * self.labels
        em, tr = w[:cut].reshape(self.dim, k), w[cut:].reshape(k, k)
        e = _emissions(features, first, em)
        start = np.zeros(len(y), bool)
        start[first] = True
        z, p, pairs = marginals_batch(e, start, tr)
        inner = np.flatnonzero(~start)
        moves = np.bincount(y[inner - 1] * k + y[inner], minlength=k * k).reshape(k, k)
        loss += z - e[np.arange(len(y)), y].sum() - (moves * tr).sum()
        up = -p
        up[np.arange(len(y)), y] += 1
        grad = np.zeros((self.dim, k))
        for j in range(k):
            own = np.ascontiguousarray(up[:, j])
            for f in range(PER_WORD):
                grad[:, j] += np.bincount(features[:, f], own, self.dim)
        begin, rest = place_features(self.dim)
        grad[begin] += up[first].sum(0)
        grad[rest] += up[inner].sum(0)
        grad = np.concatenate([grad.reshape(-1), (moves - pairs).reshape(-1)])
        place = np.flatnonzero(grad)
        grad = grad[place]
        d = grad / len(first) ** 0.5 - self.l2 * w[place]
        g[place] += d * d
        w[place] += self.alpha * d / np.sqrt(1e-3 + g[place])
        touched[place] += np.abs(grad)
        return (n + len(y), w, g, touched, loss)

    def merge(self, a, b):
        if a is None or b is None:
            return b if a is None else a
        both = a[3] + b[3]
        safe = np.where(both > 0, both, 1)
        mean = lambda x, y: np.where(both > 0, (x * a[3] + y * b[3]) / safe, x)
        return (a[0] + b[0], mean(a[1], b[1]), np.maximum(a[2], b[2]), both, a[4] + b[4])

    def finish(self, s):
        return [] if s is None else [{"n": s[0], "w": s[1].tolist(), "g": s[2].tolist(), "loss": s[4]}]


def crf_fit(blocks: DataFrame, dim: int, labels: int, epochs: int = 5, step: float = 0.5, l2: float = 1e-4) -> FitResult:
    """Weights by incremental gradients of the negative log-likelihood, from staged blocks with a label for each word. dim
    bounds the model."""
    w, log = np.zeros(dim * labels + labels * labels), IterationLog()
    g = np.zeros_like(w)
    for i in range(1, epochs + 1):
        r = run_fold(blocks, _CrfFold(w, g, dim, labels, step, l2), _CrfFold.columns).first()
        if r is None:
            break  # no tokens
        w, g = np.array(r["w"]), np.array(r["g"])
        log.append(i, loss=r["loss"] / max(1, r["n"]))
    return FitResult((w[: dim * labels].reshape(dim, labels), w[dim * labels :].reshape(labels, labels)), log, epochs, True)


def gibbs_batch(e: np.ndarray, size: np.ndarray, ids: list, trans: np.ndarray, n_iter: int, burn_in: int, seed: int = 0) -> np.ndarray:
    """Label counts by token after the burn-in, of many chains one after another. A sweep draws every label from its
    conditional: all at even places, whose neighbours are at odd ones, then all at odd places. Randomness follows from seed
    and document."""
    n, tokens = trans.shape[0], len(e)
    begin = np.cumsum(size) - size
    place = np.arange(tokens) - np.repeat(begin, size)
    order = np.argsort(place % 2, kind="stable")
    rank = np.empty(tokens, np.int64)
    rank[order] = np.arange(tokens)
    left, right = np.append(rank[:-1], 0)[np.arange(tokens) - 1], np.append(rank[1:], 0)
    left[begin] = right[begin + size - 1] = tokens  # a neighbour of label n, which weighs nothing
    left, right = left[order], right[order]
    w = np.exp(e - e.max(1, keepdims=True))[order].T.copy()
    edge = np.zeros((n + 1, n + 1))
    edge[:n, :n] = trans
    both = np.exp(edge[:, None, :n] + edge.T[None, :, :n]).reshape(-1, n).T.copy()  # by label: both neighbours at once
    u = np.empty((n_iter, tokens), np.float32)
    for d, a, t in zip(ids, begin.tolist(), size.tolist()):
        u[:, rank[a : a + t]] = np.random.default_rng([seed, d % (1 << 31) if isinstance(d, int) else zlib.crc32(str(d).encode())]).random((n_iter, t), np.float32)
    y = np.append(e.argmax(1)[order], n).astype(np.int16)
    counts = np.zeros((n, tokens), np.int32)
    half = int((place % 2 == 0).sum())
    for it in range(n_iter):
        for s in (slice(0, half), slice(half, tokens)):
            near = y[left[s]] * np.int16(n + 1) + y[right[s]]
            total = [w[0, s] * both[0][near]]
            for l in range(1, n):
                total.append(total[-1] + w[l, s] * both[l][near])
            mark = u[it, s] * total[-1]
            drawn = (mark >= total[0]).astype(np.int16)
            for l in range(1, n - 1):
                drawn += mark >= total[l]
            y[s] = drawn
        if it >= burn_in:
            for l in range(n):
                counts[l] += y[:-1] == l
    return counts.T[rank]


def crf_label(blocks: DataFrame, emission: np.ndarray, trans: np.ndarray, method: str = "viterbi", n_iter: int = 60, burn_in: int = 10, most: int = 1 << 16) -> DataFrame:
    """(doc_id, path, label) of packed documents under a trained model: each document's best labeling, or each token's most
    frequent label among samples; and the labels of its words. Samples are drawn for up to `most` tokens (or one document)
    together. The model goes to the tasks: its size is dim x labels."""
    kind = dict(blocks.dtypes)["docs"].removeprefix("array<").removesuffix(">")
    names = ["docs", *_CrfFold.columns]

    def sampled(ids: pa.Array, size: np.ndarray, e: np.ndarray) -> np.ndarray:
        ends, out, a, ids = np.cumsum(size), [], 0, ids.to_pylist()
        while a < len(size):
            begin = int(ends[a] - size[a])
            z = max(a + 1, int(np.searchsorted(ends, begin + most, side="right")))
            out.append(gibbs_batch(e[begin : ends[z - 1]], size[a:z], ids[a:z], trans, n_iter, burn_in).argmax(1))
            a = z
        return np.concatenate(out)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for ids, size, word, features, label in _unpacked(b, {c: i for i, c in enumerate(names)}):
                begin = np.cumsum(size) - size
                e = _emissions(features[word], begin, emission)
                path = viterbi_batch(e, size.astype(np.int64), trans)[1] if method == "viterbi" else sampled(ids, size, e)
                cut = pa.array(np.append(begin, len(word)).astype(np.int32))
                yield pa.RecordBatch.from_arrays([ids, *(pa.ListArray.from_arrays(cut, pa.array(x.astype(np.int32))) for x in (path, label[word]))], names=["doc_id", "path", "label"])

    return blocks.select(*names).mapInArrow(work, f"doc_id {kind}, path array<int>, label array<int>")


def label_spans(labelled: DataFrame, labels: tuple[str, ...]) -> DataFrame:
    """(doc_id, found, start, end, kind) of runs of one label other than O in each document's path (found) and labels (not
    found)."""
    kind = dict(labelled.dtypes)["doc_id"]
    outside = labels.index("O")

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for c in (1, 2):
                size = pc.list_value_length(b.column(c)).to_numpy().astype(np.int64)
                y = np.asarray(b.column(c).flatten())
                begin = np.cumsum(size) - size
                new = np.ones(len(y) + 1, bool)
                new[1:-1] = y[1:] != y[:-1]
                new[begin[size > 0]] = True
                at = np.flatnonzero(new)
                start, end = at[:-1], at[1:] - 1
                own = y[start] != outside
                start, end = start[own], end[own]
                row = np.searchsorted(begin, start, side="right") - 1
                places = [pa.array((x - begin[row]).astype(np.int32)) for x in (start, end)]
                yield pa.RecordBatch.from_arrays([b.column(0).take(pa.array(row)), pa.array(np.full(len(row), c == 1)), *places, pa.array(labels, pa.string()).take(pa.array(y[start]))], names=["doc_id", "found", "start", "end", "kind"])

    return labelled.select("doc_id", "path", "label").mapInArrow(work, f"doc_id {kind}, found boolean, start int, end int, kind string")


def hmm_fit(tagged: DataFrame, smoothing: float = 0.1) -> tuple[DataFrame, DataFrame]:
    """The baseline: (tag, token, logp) and (prev, tag, logp) from counts of (doc_id, pos, token, tag)."""
    tags = tagged.groupBy("tag").agg(F.count("*").alias("t"))
    v = tagged.select("token").distinct().count()
    emit = tagged.groupBy("tag", "token").agg(F.count("*").alias("n")).join(F.broadcast(tags), "tag").select("tag", "token", F.log((F.col("n") + smoothing) / (F.col("t") + smoothing * (v + 1))).alias("logp"))
    prev = F.lag("tag").over(Window.partitionBy("doc_id").orderBy("pos"))
    pairs = tagged.withColumn("prev", F.coalesce(prev, F.lit("^"))).groupBy("prev", "tag").agg(F.count("*").alias("n"))
    total = pairs.groupBy("prev").agg(F.sum("n").alias("t"))
    k = tags.count()
    return emit, pairs.join(F.broadcast(total), "prev").select("prev", "tag", F.log((F.col("n") + smoothing) / (F.col("t") + smoothing * k)).alias("logp"))


def spans(tagged: DataFrame) -> DataFrame:
    """(doc_id, start, end, kind, text) of runs of one tag other than O: islands by a running count of changes."""
    w = Window.partitionBy("doc_id").orderBy("pos")
    change = (F.coalesce(F.lag("tag").over(w), F.lit("")) != F.col("tag")).cast("int")
    island = tagged.withColumn("c", change).withColumn("i", F.sum("c").over(w)).filter("tag <> 'O'")
    return island.groupBy("doc_id", "i", "tag").agg(F.min("pos").alias("start"), F.max("pos").alias("end"), F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("pos", "token"))), lambda s: s["token"]), " ").alias("text")).select("doc_id", "start", "end", F.col("tag").alias("kind"), "text")


def resolve_mcmc(pairs: DataFrame, block: str, n_iter: int = 200, seed: int = 0, missing: float = 0.0) -> DataFrame:
    """(mention, entity) by Metropolis-Hastings over assignments within blocks of (block, a, b, weight): a move takes a
    mention to the entity of another or to one of its own; pair weights within entities add up to the score, where pairs
    that are not listed weigh `missing`. A row with a = b lists a mention. Entity names are the least mention. A block's
    pairs meet in one task, so memory goes with the pairs listed and not with all pairs."""

    def run(t: pa.Table) -> pa.Table:
        a, b, weight = t["a"].to_pylist(), t["b"].to_pylist(), t["weight"].to_pylist()
        names = sorted(set(a) | set(b))
        at = {n: i for i, n in enumerate(names)}
        near: list[dict[int, float]] = [{} for _ in names]
        for p, q, v in zip(a, b, weight):
            if p != q:
                near[at[p]][at[q]] = near[at[q]][at[p]] = v
        rng = np.random.default_rng([seed, len(names)])
        n = len(names)
        y, size = list(range(n)), [1] * n
        free: list[int] = []

        def pull(i: int, entity: int) -> float:
            listed = [v for j, v in near[i].items() if y[j] == entity]
            return sum(listed) + missing * (size[entity] - (y[i] == entity) - len(listed))

        for i, j, u in zip(rng.integers(n, size=n_iter * n).tolist(), rng.integers(n, size=n_iter * n).tolist(), np.log(np.maximum(rng.random(n_iter * n), 1e-300)).tolist()):
            old = y[i]
            if i == j and (size[old] == 1 or not free):
                continue  # on its own already
            new = y[j] if i != j else free[-1]
            if new == old or u >= 4 * (pull(i, new) - pull(i, old)):
                continue
            if size[new] == 0:
                free.remove(new)
            y[i], size[old], size[new] = new, size[old] - 1, size[new] + 1
            if size[old] == 0:
                free.append(old)
        least: dict[int, object] = {}
        for name, k in zip(names, y):  # names are in order
            least.setdefault(k, name)
        kind = t.schema.field("a").type
        return pa.table([pa.array(names, kind), pa.array([least[k] for k in y], kind)], names=["mention", "entity"])

    kind = dict(pairs.dtypes)["a"]
    return pairs.select(block, "a", "b", "weight").groupBy(block).applyInArrow(run, f"mention {kind}, entity {kind}")
