"""Sketches, profiles, quantiles, sampling and the bootstrap."""

from __future__ import annotations

import math
from collections.abc import Sequence
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from rowfold.core import validate
from rowfold.functions.portable import M, carter_wegman, mixed, uniform

# --- count-min -------------------------------------------------------------------------------------------------------


def cm_shape(eps: float, delta: float) -> tuple[int, int]:
    """(width, depth) for an overcount of at most eps * N with probability 1 - delta."""
    return math.ceil(math.e / eps), math.ceil(math.log(1 / delta))


def countmin(df: DataFrame, col: str, width: int, depth: int, by: Sequence[str] = (), level: int = 0) -> DataFrame:
    """(by, row, bucket, cnt): cells of the sketch. Values are counted first, so that hashing and shuffling are by
    distinct value; sketches of parts add up cell by cell. level: counts dyadic intervals of 2**level instead."""
    v = F.shiftright(F.col(col).cast("long"), level) if level else F.col(col).cast("long")
    each = df.filter(F.col(col).isNotNull()).groupBy(*by, v.alias("v")).agg(F.count("*").alias("n"))
    cells = F.explode(F.array(*[F.struct(F.lit(r).alias("row"), carter_wegman(F.col("v"), r, width).alias("bucket")) for r in range(depth)]))
    return each.select(*by, cells.alias("c"), "n").groupBy(*by, "c.row", "c.bucket").agg(F.sum("n").alias("cnt"))


def cm_point(cells: DataFrame, probes: DataFrame, value: str, width: int, depth: int) -> DataFrame:
    """(value, estimate): the least of the value's cells; a missing cell is 0."""
    want = probes.select(value).distinct().select(value, F.explode(F.array(*[F.struct(F.lit(r).alias("row"), carter_wegman(F.col(value), r, width).alias("bucket")) for r in range(depth)])).alias("c")).select(value, "c.row", "c.bucket")
    return want.join(cells, ["row", "bucket"], "left").groupBy(value).agg(F.min(F.coalesce("cnt", F.lit(0))).alias("estimate"))


def cm_dyadic(df: DataFrame, col: str, width: int, depth: int, levels: int) -> DataFrame:
    """Sketches of all dyadic levels: (level, row, bucket, cnt), in one pass over distinct values."""
    each = df.filter(F.col(col).isNotNull()).groupBy(F.col(col).cast("long").alias("v")).agg(F.count("*").alias("n"))
    lv = each.select("n", F.posexplode(F.array(*[F.shiftright("v", k) for k in range(levels)])).alias("level", "v"))
    cells = F.explode(F.array(*[F.struct(F.lit(r).alias("row"), carter_wegman(F.col("v"), r, width).alias("bucket")) for r in range(depth)]))
    return lv.select("level", cells.alias("c"), "n").groupBy("level", "c.row", "c.bucket").agg(F.sum("n").alias("cnt"))


def dyadic_cover(low: int, high: int, levels: int) -> list[tuple[int, int]]:
    """(level, index) of the fewest dyadic intervals that make up [low, high]."""
    out = []
    while low <= high:
        k = 0
        while k + 1 < levels and low % (1 << (k + 1)) == 0 and low + (1 << (k + 1)) - 1 <= high:
            k += 1
        out.append((k, low >> k))
        low += 1 << k
    return out


def cm_range(cells: DataFrame, ranges: Sequence[tuple[int, int]], width: int, depth: int, levels: int) -> DataFrame:
    """(low, high, estimate) from the dyadic sketches."""
    spark = cells.sparkSession
    rows = [(a, b, k, i) for a, b in ranges for k, i in dyadic_cover(a, b, levels)]
    want = spark.createDataFrame(rows, "low long, high long, level int, v long")
    want = want.select("low", "high", "level", "v", F.explode(F.array(*[F.struct(F.lit(r).alias("row"), carter_wegman(F.col("v"), r, width).alias("bucket")) for r in range(depth)])).alias("c")).select("low", "high", "level", "v", "c.row", "c.bucket")
    got = want.join(cells, ["level", "row", "bucket"], "left").groupBy("low", "high", "level", "v").agg(F.min(F.coalesce("cnt", F.lit(0))).alias("e"))
    return got.groupBy("low", "high").agg(F.sum("e").alias("estimate"))


def cm_dot(a: DataFrame, b: DataFrame) -> DataFrame:
    """Upper estimate of the inner product of two frequency vectors sketched alike."""
    return a.join(b.select("row", "bucket", F.col("cnt").alias("other")), ["row", "bucket"]).groupBy("row").agg(F.sum(F.col("cnt") * F.col("other")).alias("p")).agg(F.min("p").alias("dot"))


def cm_quantile(cells: DataFrame, q: float, total: int, width: int, depth: int, levels: int) -> int:
    """A value whose rank is about q * total, walking down the dyadic levels; a handful of cells a level come back."""
    want, low = max(1, math.ceil(q * total)), 0
    for k in range(levels - 1, -1, -1):
        probe = cells.sparkSession.createDataFrame([(low >> k,)], "v long")
        n = cm_point(cells.filter(F.col("level") == k), probe, "v", width, depth).first()["estimate"]
        if n < want:
            want -= n
            low += 1 << k
    return low


def heavy_hitters(df: DataFrame, col: str, share: float, width: int, depth: int) -> DataFrame:
    """(value, estimate) of values whose sketched count reaches share of all rows. Probes are the distinct values."""
    n = df.filter(F.col(col).isNotNull()).count()
    cells = countmin(df, col, width, depth)
    return cm_point(cells, df.filter(F.col(col).isNotNull()).select(F.col(col).cast("long").alias("value")), "value", width, depth).filter(F.col("estimate") >= share * n)


# --- distinct counts -------------------------------------------------------------------------------------------------


def _low_bit(x: Column) -> Column:
    """Place of the lowest set bit; 30 for zero."""
    return F.when(x == 0, 30).otherwise(F.bit_count((x.bitwiseAND(-x) - 1).cast("long")))


def fm_bitmaps(df: DataFrame, col: str, maps: int = 64, by: Sequence[str] = ()) -> DataFrame:
    """(by, map, bits): bit maps of lowest set bits with stochastic averaging; those of parts combine by bitwise or."""
    h = mixed(F.col(col).cast("long"), 1)
    m, rest = F.pmod(h, F.lit(maps)), F.floor(h / maps).cast("long")
    return df.filter(F.col(col).isNotNull()).groupBy(*by, m.alias("map")).agg(F.bit_or(F.call_function("shiftleft", F.lit(1).cast("long"), _low_bit(rest).cast("int"))).alias("bits"))


def fm_estimate(bitmaps: DataFrame, maps: int = 64, by: Sequence[str] = ()) -> DataFrame:
    """(by, estimate, standard error). Where many maps are empty, the count of empty maps decides."""
    first_zero = _low_bit(F.bitwise_not("bits"))
    agg = bitmaps.groupBy(*by).agg(F.sum(first_zero).alias("r"), F.count("*").alias("used"))
    large = maps / 0.77351 * F.pow(F.lit(2.0), F.col("r") / maps)
    small = -maps * F.log((maps - F.col("used")) / F.lit(float(maps)))
    return agg.select(*by, F.round(F.when(F.col("used") < maps, small).otherwise(large)).cast("long").alias("estimate"), F.lit(0.78 / math.sqrt(maps)).alias("std_error"))


def fm_distinct(df: DataFrame, col: str, maps: int = 64, by: Sequence[str] = ()) -> DataFrame:
    return fm_estimate(fm_bitmaps(df, col, maps, by), maps, by)


def distinct_count(df: DataFrame, col: str, method: str = "exact") -> DataFrame:
    c = F.col(col)
    made = {"exact": F.countDistinct(c), "hll": F.hll_sketch_estimate(F.hll_sketch_agg(c.cast("string"))), "approx": F.approx_count_distinct(c), "theta": F.theta_sketch_estimate(F.theta_sketch_agg(c.cast("string"))) if hasattr(F, "theta_sketch_agg") else F.approx_count_distinct(c)}
    if method == "fm":
        return fm_distinct(df, col).select(F.col("estimate").alias("n"))
    return df.agg(made[method].cast("long").alias("n"))


# --- profile ---------------------------------------------------------------------------------------------------------


def profile(df: DataFrame, distinct: str = "hll", quartiles: bool = True) -> DataFrame:
    """One row per column: name, type, rows, nulls, distinct values, least, greatest and mean value or length, spread, quartiles.

    The columns are read from the schema and become one aggregate over one scan. distinct: exact, hll or none."""
    validate.columns(df, *df.columns)
    aggs, rows = [F.count("*").alias("n")], []
    for i, f in enumerate(df.schema.fields):
        c, t = F.col(validate.quoted(f.name)), f.dataType
        num = isinstance(t, T.NumericType)
        size = F.size(c) if isinstance(t, (T.ArrayType, T.MapType)) else F.length(c.cast("string")) if isinstance(t, (T.StringType, T.BinaryType)) else None
        measure = c.cast("double") if num else size.cast("double") if size is not None else None
        text = lambda x: x.cast("string")
        plain = not isinstance(t, (T.ArrayType, T.MapType, T.StructType))
        key = c if plain else F.xxhash64(c)
        parts = {
            "filled": F.count(c), "uniq": F.approx_count_distinct(key) if distinct == "hll" else F.lit(None).cast("long"),
            "least": text(F.min(c)) if plain else F.lit(None).cast("string"), "most": text(F.max(c)) if plain else F.lit(None).cast("string"),
            "mean": F.avg(measure) if measure is not None else F.lit(None).cast("double"), "std": F.stddev_samp(measure) if measure is not None else F.lit(None).cast("double"),
            "qs": F.percentile_approx(measure, [0.25, 0.5, 0.75], 10000) if measure is not None and quartiles else F.lit(None).cast("array<double>"),
        }
        aggs += [v.alias(f"{k}{i}") for k, v in parts.items()]
        g = lambda k: F.col(f"{k}{i}")  # noqa: E731, B023
        rows.append(F.struct(F.lit(i).alias("pos"), F.lit(f.name).alias("column"), F.lit(t.simpleString()).alias("type"), F.col("n").alias("rows"), (F.col("n") - g("filled")).alias("nulls"), g("uniq").alias("distinct"), g("least").alias("min"), g("most").alias("max"), g("mean").alias("mean"), g("std").alias("std"), F.get(g("qs"), F.lit(0)).alias("q25"), F.get(g("qs"), F.lit(1)).alias("q50"), F.get(g("qs"), F.lit(2)).alias("q75")))
    out = df.agg(*aggs).select(F.explode(F.array(*rows)).alias("r")).select("r.*")
    if distinct != "exact":
        return out
    # one table of (column, value) is deduplicated for all columns together, so a row is not expanded once per column
    # with all its other values beside it
    keys = [F.struct(F.lit(i).alias("pos"), (F.col(validate.quoted(f.name)) if not isinstance(f.dataType, (T.ArrayType, T.MapType, T.StructType)) else F.when(F.col(validate.quoted(f.name)).isNotNull(), F.xxhash64(validate.quoted(f.name)))).cast("string").alias("v")) for i, f in enumerate(df.schema.fields)]
    seen = df.select(F.explode(F.array(*keys)).alias("k")).select("k.*").filter("v is not null").distinct().groupBy("pos").agg(F.count("*").alias("uniq"))
    return out.join(F.broadcast(seen), "pos", "left").withColumn("distinct", F.coalesce("uniq", F.lit(0).cast("long"))).drop("uniq").select(*out.columns)


def top_values(df: DataFrame, col: str, k: int = 10) -> DataFrame:
    """The k most frequent values, ties to the lesser value."""
    return df.groupBy(F.col(col).cast("string").alias("value")).agg(F.count("*").alias("n")).orderBy(F.desc("n"), F.asc_nulls_first("value")).limit(k)


# --- quantiles -------------------------------------------------------------------------------------------------------


def quantile(df: DataFrame, col: str, qs: Sequence[float], method: str = "exact", by: Sequence[str] = ()) -> DataFrame:
    """(by, q, value). exact: interpolated; discrete: a value that occurs; approx: rank error 1/10000; kll: a mergeable
    sketch; bisect: exact discrete by counting passes, without sorting or shuffling rows."""
    c = F.col(col).cast("double")
    if method == "bisect":
        return df.sparkSession.createDataFrame([(float(q), quantile_bisect(df, col, q)) for q in qs], "q double, value double")
    if method == "kll":
        sk = df.groupBy(*by).agg(F.kll_sketch_agg_double(c).alias("s"))
        return sk.select(*by, F.explode(F.array(*[F.struct(F.lit(float(q)).alias("q"), F.kll_sketch_get_quantile_double("s", F.lit(float(q))).alias("value")) for q in qs])).alias("r")).select(*by, "r.*")
    one = {
        "exact": lambda q: F.percentile(c, F.lit(float(q))),
        "discrete": lambda q: F.expr(f"percentile_disc({float(q)}) within group (order by cast({validate.quoted(col)} as double))"),
        "approx": lambda q: F.percentile_approx(c, float(q), 10000),
    }[method]
    agg = df.groupBy(*by).agg(*[one(q).alias(f"q{i}") for i, q in enumerate(qs)])
    return agg.select(*by, F.explode(F.array(*[F.struct(F.lit(float(q)).alias("q"), F.col(f"q{i}").alias("value")) for i, q in enumerate(qs)])).alias("r")).select(*by, "r.*")


def quantile_bisect(df: DataFrame, col: str, q: float, bins: int = 1024, few: int = 4096) -> float | None:
    """The value of rank ceil(q n): histograms of one range after another, each zooming into the bin that holds the rank,
    until the bin's values are few distinct ones. Every pass sends back one number per bin."""
    c = F.col(col).cast("double")
    n, low, high = df.agg(F.count(c), F.min(c), F.max(c)).first()
    if not n:
        return None
    rank = max(1, math.ceil(q * n - 1e-12))
    for _ in range(60):
        if low == high:
            return low
        inside = df.filter(c.between(low, high))
        width = (high - low) / bins
        if width == 0 or low + width == low:
            inside_few = True
        else:
            inside_few = inside.select(F.approx_count_distinct(c)).first()[0] <= few // 2
        if inside_few:
            got = sorted((r["v"], r["n"]) for r in inside.groupBy(c.alias("v")).agg(F.count("*").alias("n")).limit(8 * few).collect())
            for v, k in got:
                rank -= k
                if rank <= 0:
                    return v
            raise RuntimeError("more values than expected in one bin")
        b = F.least(F.floor((c - low) / width), F.lit(bins - 1)).cast("int")
        hist = sorted((r["b"], r["n"], r["lo"], r["hi"]) for r in inside.groupBy(b.alias("b")).agg(F.count("*").alias("n"), F.min(c).alias("lo"), F.max(c).alias("hi")).collect())
        for _, k, lo, hi in hist:
            if rank <= k:
                low, high = lo, hi
                break
            rank -= k
    return low


# --- sampling and the bootstrap --------------------------------------------------------------------------------------


def sample_rows(df: DataFrame, key: str, share: float, seed: int = 0) -> DataFrame:
    """Rows whose portable uniform number falls below share: the same rows on any engine and any partitioning."""
    return df.filter(uniform(F.col(key), seed) < share)


def stratified(df: DataFrame, key: str, col: str, shares: dict, seed: int = 0) -> DataFrame:
    limit = reduce(lambda c, kv: c.when(F.col(col) == kv[0], F.lit(float(kv[1]))), shares.items(), F.when(F.lit(False), F.lit(0.0)))
    return df.filter(uniform(F.col(key), seed) < F.coalesce(limit, F.lit(0.0)))


def poisson_times(u: Column, rate: float, most: int = 12) -> Column:
    """How often a row is drawn: the inverse distribution function of a Poisson number at u."""
    p, cum, out = math.exp(-rate), 0.0, None
    for k in range(most):  # a chain of cases stops at the first that holds, mostly the first or second
        cum += p
        out = F.when(u < cum, k) if out is None else out.when(u < cum, k)
        p *= rate / (k + 1)
    return out.otherwise(most)


def bootstrap(df: DataFrame, key: str, value: str, trials: int, m: int | None = None, seed: int = 0, with_replacement: bool = True) -> DataFrame:
    """(trial, n, mean) of resampled rows, all trials in one pass: a row's multiplicity in a trial follows from its key
    and the trial's number alone, so no sample is ever stored and partial sums by trial are all that is shuffled."""
    n = df.filter(F.col(value).isNotNull()).count() if m is not None else 1
    rate = (m / n) if m is not None and n else 1.0
    # a virtual table of trials, as part of each row
    each = df.filter(F.col(value).isNotNull()).select(F.col(key).alias("k"), F.col(value).cast("double").alias("v"), F.explode(F.sequence(F.lit(0), F.lit(trials - 1))).alias("trial"))
    u = uniform(F.col("k"), F.col("trial"), seed)
    times = poisson_times(u, rate) if with_replacement else (u < rate).cast("int")
    w = each.withColumn("t", times).filter("t > 0")
    return w.groupBy("trial").agg(F.sum("t").cast("long").alias("n"), (F.sum(F.col("t") * F.col("v")) / F.sum("t")).alias("mean"))


def bootstrap_summary(reps: DataFrame, col: str = "mean", ci: float = 0.95) -> DataFrame:
    a = (1 - ci) / 2
    return reps.agg(F.count("*").alias("trials"), F.avg(col).alias("mean"), F.stddev_samp(col).alias("std_err"), F.percentile(col, F.lit(a)).alias("low"), F.percentile(col, F.lit(1 - a)).alias("high"))


# --- linear systems --------------------------------------------------------------------------------------------------


def cg_solve(matvec, b, tol: float = 1e-10, max_iter: int | None = None):
    """Solve a symmetric positive definite system given only products with it. b: numpy vector."""
    import numpy as np

    x = np.zeros_like(b)
    r = b - matvec(x)
    p, rs = r.copy(), float(r @ r)
    target = tol * max(1e-300, float(np.sqrt(b @ b)))
    for i in range(max_iter or 3 * len(b)):
        if math.sqrt(rs) <= target:
            break
        ap = matvec(p)
        a = rs / float(p @ ap)
        x, r = x + a * p, r - a * ap
        new = float(r @ r)
        p, rs = r + new / rs * p, new
        if (i + 1) % len(b) == 0:  # conjugacy wears off
            r = b - matvec(x)
            p, rs = r.copy(), float(r @ r)
    return x


def triple_matvec(m: DataFrame, d: int):
    """Products with a matrix of rows (i, j, v): a join with the vector on j and sums by i."""
    import numpy as np

    def times(v):
        vec = m.sparkSession.createDataFrame([(k, float(x)) for k, x in enumerate(v)], "j int, x double")
        out = np.zeros(d)
        for r in m.join(F.broadcast(vec), "j").groupBy("i").agg(F.sum(F.col("v") * F.col("x")).alias("s")).collect():
            out[r["i"]] = r["s"]
        return out

    return times
