"""k-means: Lloyd's rounds with implicit, explicit or fused assignments.

Centres are small and travel to the rows. Implicit rounds compute the nearest of
the previous and of the current centres in one pass; explicit rounds keep the
assignment as a column and need a pass to assign and one to average; a fused round
does both in one pass over the stored rows, whose map stage gives the next
version of the rows and one partial sum per centre.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rowfold.core import validate
from rowfold.core.bridge import matrix
from rowfold.core.driver import FitResult, IterationLog, stage
from rowfold.core.fold import Fold, run_fold

DISTANCES = ("sqeuclid", "l1", "cosine", "tanimoto")


def distances(x: np.ndarray, c: np.ndarray, kind: str = "sqeuclid") -> np.ndarray:
    """(n, k) distances of rows to centres."""
    if kind == "sqeuclid":
        return np.maximum((x * x).sum(1)[:, None] - 2 * (x @ c.T) + (c * c).sum(1), 0)
    if kind == "l1":
        return np.stack([np.abs(x - v).sum(1) for v in c], axis=1)
    dot, nx, nc = x @ c.T, (x * x).sum(1)[:, None], (c * c).sum(1)
    if kind == "cosine":
        return 1 - dot / np.maximum(np.sqrt(nx * nc), 1e-300)
    if kind == "tanimoto":
        return 1 - dot / np.maximum(nx + nc - dot, 1e-300)
    raise validate.InputError("UNKNOWN_DISTANCE", f"no distance {kind!r}", ", ".join(DISTANCES))


def nearest(x: np.ndarray, c: np.ndarray, kind: str = "sqeuclid") -> tuple[np.ndarray, np.ndarray]:
    """Number of the nearest centre of each row, the least on ties, and the distance. Distances are compared at ten
    significant digits, so that the way of summing does not decide ties."""
    d = distances(x, c, kind)
    at = np.round(d, 10).argmin(1)
    return at, d[np.arange(len(x)), at]


def nearest_centre(x: str, centres: list[list[float]]) -> Column:
    """The nearest column of a matrix of centres, as an expression: struct(dist, idx)."""
    m = F.array(*[F.array(*map(F.lit, map(float, c))) for c in centres])
    dist = lambda c: F.aggregate(F.zip_with(F.col(x).cast("array<double>"), c, lambda p, q: (p - q) * (p - q)), F.lit(0.0), lambda s, v: s + v)
    return F.array_min(F.transform(m, lambda c, i: F.struct(F.round(dist(c), 10).alias("dist"), i.alias("idx"))))


PARTIAL = "centre int, total array<double>, n long, moved long, sse double, evaluations long"


class LloydFold(Fold):
    """Per centre: sum and number of its rows; over all: rows that changed centre, squared distances, evaluations."""

    schema = PARTIAL

    def __init__(self, current: np.ndarray, previous: np.ndarray | None, kind: str):
        self.current, self.previous, self.kind = current, previous, kind

    def zero(self):
        k, d = self.current.shape
        return [np.zeros((k, d)), np.zeros(k, np.int64), 0, 0.0, 0]

    def step(self, s, batch: pa.RecordBatch):
        x = matrix(batch.column(0))
        at, dist = nearest(x, self.current, self.kind)
        k = len(self.current)
        moved = len(x) if self.previous is None else int((nearest(x, self.previous, self.kind)[0] != at).sum())
        member = np.zeros((len(x), k))
        member[np.arange(len(x)), at] = 1
        return self.merge(s, [member.T @ x, np.bincount(at, minlength=k), moved, float(dist.sum()), len(x) * k * (1 if self.previous is None else 2)])

    def merge(self, a, b):
        return [p + q for p, q in zip(a, b)]

    def finish(self, s):
        return [{"centre": i, "total": s[0][i].tolist(), "n": int(s[1][i]), "moved": s[2], "sse": s[3], "evaluations": s[4]} for i in range(len(s[1]))]


def _means(rows: list, old: np.ndarray) -> np.ndarray:
    new = old.copy()
    for r in rows:
        if r["n"]:
            new[r["centre"]] = np.array(r["total"]) / r["n"]
    return new


def seed(df: DataFrame, x: str, k: int, method: str = "random", seed: int = 0, id_col: str | None = None, oversample: float = 2.0, rounds: int = 4) -> np.ndarray:
    """k starting centres. first: least ids; random: hash order; plusplus: each next row drawn in proportion to its squared
    distance from the chosen ones; parallel: rows drawn so in a few oversampling rounds, then weighted and reduced."""
    src = df.select(*( [id_col] if id_col else []), F.col(x).cast("array<double>").alias("x")).filter(F.col("x").isNotNull())
    key = F.xxhash64(F.lit(seed), F.col(id_col) if id_col else F.col("x"))
    if method == "first":
        got = src.orderBy(id_col).limit(k).collect()
    elif method == "random":
        got = src.orderBy(key, "x").limit(k).collect()
    elif method in ("plusplus", "parallel"):
        chosen = [np.array(r["x"]) for r in src.orderBy(key, "x").limit(1).collect()]
        draw = lambda i: (F.pmod(F.xxhash64(F.lit(seed), F.lit(i), F.col("x")), F.lit(1 << 52)) + 1) / float(1 << 52)
        if method == "plusplus":
            while len(chosen) < k:  # the least of exponential keys with weights as rates is a draw in proportion to the weights
                dist = nearest_centre("x", [c.tolist() for c in chosen])["dist"]
                r = src.withColumn("w", dist).filter("w > 0").orderBy(-F.log(draw(len(chosen))) / F.col("w"), "x").limit(1).collect()
                if not r:
                    break
                chosen.append(np.array(r[0]["x"]))
            return np.array(chosen)
        for i in range(rounds):
            dist = src.withColumn("w", nearest_centre("x", [c.tolist() for c in chosen])["dist"])
            total = dist.agg(F.sum("w")).first()[0] or 0.0
            if not total:
                break
            # expected oversample * k rows a round, so what comes to the driver is bounded by the model
            chosen += [np.array(r["x"]) for r in dist.filter(draw(i + 1) < oversample * k * F.col("w") / total).select("x").collect()]
        c = np.unique(np.array(chosen), axis=0)
        weight = np.array([r["n"] for r in sorted(run_fold(src, LloydFold(c, None, "sqeuclid"), ["x"]).collect(), key=lambda r: r["centre"])], float)
        picks = [int(weight.argmax())]
        while len(picks) < min(k, len(c)):
            d = distances(c, c[picks]).min(1) * weight
            picks.append(int(d.argmax()))
        return c[picks]
    else:
        raise validate.InputError("UNKNOWN_SEEDING", f"no seeding {method!r}", "first, random, plusplus or parallel")
    return np.array([r["x"] for r in got], float)


def kmeans(
    df: DataFrame, x: str, k: int, id_col: str, assign: str = "implicit", init: np.ndarray | None = None, seed_method: str = "random", max_iter: int = 20,
    min_frac_reassigned: float = 0.001, tol: float = 0.0, distance: str = "sqeuclid", empty: str = "keep", random_seed: int = 0, stage_mode: str = "copy",
) -> FitResult:
    """Centres, with the log of rounds: objective before the update, rows reassigned, distance evaluations, passes.

    assign: implicit, explicit or fused. stage_mode (explicit): "copy" writes all rows anew, "delta" only the rows whose
    centre changed, which stand before the older versions when read. empty: keep a centre without rows, or reseed it at
    the row farthest from its centre. frame: (centre, point).
    """
    validate.vector(df, x)
    src = df.select(F.col(id_col).alias("id"), F.col(x).cast("array<double>").alias("x")).filter(F.col("x").isNotNull())
    c = np.array(init, float) if init is not None else seed(df, x, k, seed_method, random_seed, id_col)
    log, previous, moved = IterationLog(), None, None
    spark = df.sparkSession
    src = src.persist() if assign == "implicit" else src
    rows = None if assign == "implicit" else stage(src.withColumn("cid", F.lit(-1)), "kmeans")
    n = src.count()
    converged, i = False, 0

    def relabel(batches: Iterator[pa.RecordBatch], centres: np.ndarray) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                at, _ = nearest(matrix(b.column(1)), centres, distance)
                yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(at.astype(np.int32)), pa.array(at != np.asarray(b.column(2)))], names=["id", "x", "cid", "changed"])

    kind = dict(src.dtypes)["id"]
    for i in range(1, max_iter + 1):
        if assign == "implicit":
            got = run_fold(src, LloydFold(c, previous, distance), ["x"]).collect()
            moved, sse, evals, passes = got[0]["moved"], got[0]["sse"], got[0]["evaluations"], 1
            new = _means(got, c)
            counts = {r["centre"]: r["n"] for r in got}
        elif assign == "explicit":
            now = c
            next_rows = rows.mapInArrow(lambda it, now=now: relabel(it, now), f"id {kind}, x array<double>, cid int, changed boolean")
            if stage_mode == "delta":
                changed = stage(next_rows.filter("changed").drop("changed"), "kmeans-delta")
                moved = changed.count()
                rows = rows.join(changed.select("id"), "id", "left_anti").unionByName(changed)
                rows = stage(rows, "kmeans") if i % 5 == 0 else rows
            else:
                full = stage(next_rows, "kmeans")
                moved = full.filter("changed").count()
                rows = full.drop("changed")
            got = _centre_sums(rows, c)
            sse, evals, passes = got["sse"], n * len(c), 2
            new, counts = _means(got["rows"], c), {r["centre"]: r["n"] for r in got["rows"]}
        else:
            now = c

            def fused(batches: Iterator[pa.RecordBatch], now=now) -> Iterator[pa.RecordBatch]:
                total, count, sse = np.zeros(now.shape), np.zeros(len(now), np.int64), 0.0
                id_type = None
                for b in batches:
                    id_type = b.column(0).type
                    if not b.num_rows:
                        continue
                    x = matrix(b.column(1))
                    at, dist = nearest(x, now, distance)
                    np.add.at(total, at, x)
                    count += np.bincount(at, minlength=len(now))
                    sse += float(dist.sum())
                    rows_out = [b.column(0), b.column(1), pa.array(at.astype(np.int32)), pa.array(at != np.asarray(b.column(2))), pa.nulls(len(x), pa.int64()), pa.nulls(len(x), pa.float64())]
                    yield pa.RecordBatch.from_arrays(rows_out, names=["id", "x", "cid", "changed", "n", "sse"])
                keep = np.flatnonzero(count)
                if not len(keep):
                    return
                yield pa.RecordBatch.from_arrays([pa.nulls(len(keep), id_type), pa.array(total[keep].tolist(), pa.list_(pa.float64())), pa.array(keep.astype(np.int32)), pa.nulls(len(keep), pa.bool_()), pa.array(count[keep]), pa.array(np.where(np.arange(len(keep)) == 0, sse, 0.0))], names=["id", "x", "cid", "changed", "n", "sse"])

            full = stage(rows.mapInArrow(fused, f"id {kind}, x array<double>, cid int, changed boolean, n long, sse double"), "kmeans-fused")
            part = full.filter("n is not null")
            sums = part.select("cid", "n", "sse", F.posexplode("x")).groupBy("cid", "pos").agg(F.sum("col").alias("s"))
            heads = {r["cid"]: r for r in part.groupBy("cid").agg(F.sum("n").alias("n"), F.sum("sse").alias("sse")).collect()}  # k rows
            new = c.copy()
            for r in sums.collect():  # k * d numbers
                new[r["cid"], r["pos"]] = r["s"] / heads[r["cid"]]["n"]
            moved = full.filter("changed").count()
            sse, evals, passes = sum(r["sse"] for r in heads.values()), n * len(c), 1
            counts = {j: r["n"] for j, r in heads.items()}
            rows = full.filter("n is null").drop("changed", "n", "sse")
        lost = [j for j in range(len(c)) if not counts.get(j)]
        if lost and empty == "reseed":
            far = src.withColumn("w", nearest_centre("x", new.tolist())["dist"]).orderBy(F.desc("w"), "id").limit(len(lost)).collect()
            for j, r in zip(lost, far):
                new[j] = np.array(r["x"])
        shift = float(np.abs(new - c).max())
        log.append(i, objective=sse, moved=moved, evaluations=evals, passes=passes, shift=shift)
        previous, c = c, new
        if moved <= min_frac_reassigned * n and i > 1 or shift <= tol and tol > 0:
            converged = True
            break
    if assign == "implicit":
        src.unpersist()
    frame = spark.createDataFrame([(j, [float(v) for v in row]) for j, row in enumerate(c)], "centre int, point array<double>")
    return FitResult(c, log, i, converged, frame)


def _centre_sums(rows: DataFrame, c: np.ndarray) -> dict:
    """The second pass of an explicit round: averages by the stored assignment, as plain aggregates."""
    sums = rows.select("cid", F.posexplode("x")).groupBy("cid", "pos").agg(F.sum("col").alias("s"), F.count("*").alias("n"), F.sum(F.col("col") * F.col("col")).alias("q"))
    got = sums.collect()  # k * d numbers
    by: dict[int, dict] = {}
    sse = 0.0
    for r in got:
        e = by.setdefault(r["cid"], {"centre": r["cid"], "total": [0.0] * c.shape[1], "n": r["n"]})
        e["total"][r["pos"]] = r["s"]
        m = c[r["cid"], r["pos"]]
        sse += r["q"] - 2 * m * r["s"] + r["n"] * m * m
    return {"rows": list(by.values()), "sse": sse}


def predict_kmeans(df: DataFrame, x: str, centres: np.ndarray) -> DataFrame:
    near = nearest_centre(x, [list(map(float, c)) for c in centres])
    return df.withColumn("near", near).withColumn("cid", F.col("near.idx")).withColumn("dist", F.col("near.dist")).drop("near")


def silhouette(df: DataFrame, x: str, cid: str) -> DataFrame:
    """Mean simplified silhouette: distances to cluster means instead of to all rows, in two passes."""
    means = df.select(cid, F.posexplode(F.col(x).cast("array<double>"))).groupBy(cid, "pos").agg(F.avg("col").alias("m")).groupBy(cid).agg(F.transform(F.array_sort(F.collect_list(F.struct("pos", "m"))), lambda s: s["m"]).alias("m")).orderBy(cid).collect()
    ms = F.array(*[F.struct(F.lit(r[cid]).alias("c"), F.array(*map(F.lit, r["m"])).alias("m")) for r in means])
    d = F.transform(ms, lambda s: F.struct(F.sqrt(F.aggregate(F.zip_with(F.col(x).cast("array<double>"), s["m"], lambda p, q: (p - q) * (p - q)), F.lit(0.0), lambda a, v: a + v)).alias("d"), s["c"].alias("c")))
    e = df.withColumn("ds", d).withColumn("a", F.array_min(F.transform(F.filter("ds", lambda s: s["c"] == F.col(cid)), lambda s: s["d"]))).withColumn("b", F.array_min(F.transform(F.filter("ds", lambda s: s["c"] != F.col(cid)), lambda s: s["d"])))
    return e.agg(F.avg((F.col("b") - F.col("a")) / F.greatest("a", "b")).alias("silhouette"))


def purity(df: DataFrame, cid: str, label: str) -> DataFrame:
    each = df.groupBy(cid, label).count().groupBy(cid).agg(F.max("count").alias("top"), F.sum("count").alias("n"))
    return each.agg((F.sum("top") / F.sum("n")).alias("purity"))
