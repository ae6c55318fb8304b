"""Fixtures as DataFrames and as SQL, and SQL written from rules."""

from __future__ import annotations

from itertools import permutations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rowfold.functions.portable import M

INSULTS = "trash|scum|idiot|clown|worthless|moron|pathetic|loser|stupid|disgusting"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def words(c: str):
    """Number of runs of anything but blanks and line ends."""
    return F.size(F.filter(F.split(F.col(c), r"[ \n\t\r]+"), lambda w: w != "")).cast("double")


WORDS_SQL = "cast(len(list_filter(string_split_regex(text, '[ \\n\\t\\r]+'), lambda w: w <> '')) as double)"


def toxic(spark: SparkSession, sf_dir: str, noisy: bool = False) -> DataFrame:
    """(doc_id, lang, x, y): toxic on (1, ln n_chars), or a noisy label on (1, has an insult, ln n_chars)."""
    d = table(spark, sf_dir, "documents").select("doc_id", "lang", "n_chars", *(["text"] if noisy else [])).join(table(spark, sf_dir, "labels").select("doc_id", "toxic"), "doc_id")
    ln = F.log(F.greatest(F.col("n_chars"), F.lit(1)).cast("double"))
    if not noisy:
        return d.select("doc_id", "lang", F.array(F.lit(1.0), ln).alias("x"), F.col("toxic").cast("double").alias("y"))
    hit = F.lower("text").rlike(INSULTS).cast("double")
    flip = F.pmod((F.col("doc_id") * 7919 + 42) * 16807, F.lit(M)) / M < 0.1
    return d.select("doc_id", "lang", F.array(F.lit(1.0), hit, ln).alias("x"), F.when(flip, 1 - F.col("toxic")).otherwise(F.col("toxic")).cast("double").alias("y"))


TOXIC_SQL = "select d.doc_id, d.lang, 1.0::double as x0, ln(greatest(d.n_chars, 1)::double) as x1, l.toxic::double as y from documents d join labels l using (doc_id)"
NOISY_SQL = (
    f"select d.doc_id, 1.0::double as x0, regexp_matches(lower(d.text), '{INSULTS}')::int::double as x1, ln(greatest(d.n_chars, 1)::double) as x2, "
    f"(case when ((d.doc_id * 7919 + 42) * 16807 % {M}) / {M}.0::double < 0.1 then 1 - l.toxic else l.toxic end)::double as y from documents d join labels l using (doc_id)"
)


def det(m: list[list[str]]) -> str:
    """A determinant as an expression."""
    n = len(m)
    out = []
    for p in permutations(range(n)):
        sign = 1
        for i in range(n):
            for j in range(i):
                sign *= -1 if p[j] > p[i] else 1
        out.append(("+" if sign > 0 else "-") + "*".join(f"({m[i][p[i]]})" for i in range(n)))
    return "(" + "".join(out) + ")"


def gram(d: int) -> list[list[str]]:
    return [[f"g{max(i, j)}_{min(i, j)}" for j in range(d)] for i in range(d)]


def sums_sql(src: str, d: int, by: str = "", weight: str = "") -> str:
    w = f"{weight} * " if weight else ""
    cols = ["count(*) as n", f"sum({w}y) as sy", f"sum({w}y * y) as syy"]
    cols += [f"sum({w}x{i} * y) as xy{i}" for i in range(d)] + [f"sum({w}x{i} * x{j}) as g{i}_{j}" for i in range(d) for j in range(i + 1)]
    return f"select {by + ', ' if by else ''}{', '.join(cols)} from ({src}) {'group by ' + by if by else ''}"


def ols_sql(src: str, d: int, by: str = "", digits: int = 4) -> str:
    """pos, coef, std_err, t_stat, r2, n by Cramer's rule on the sums of (x0.., y)."""
    g = gram(d)
    swap = lambda k: [[g[i][j] if j != k else f"xy{i}" for j in range(d)] for i in range(d)]
    minor = lambda k: [[g[i][j] for j in range(d) if j != k] for i in range(d) if i != k]
    key = f"{by}, " if by else ""
    coefs = ", ".join(f"{det(swap(k))} / {det(g)} as b{k}" for k in range(d))
    inv = ", ".join(f"({det(minor(k)) if d > 1 else '1'}) / {det(g)} as v{k}" for k in range(d))
    sse = "(syy - (" + " + ".join(f"b{k} * xy{k}" for k in range(d)) + "))"
    rows = " union all ".join(f"select {key}{k} as pos, round(b{k}, {digits}) as coef, round(sqrt(v{k} * sse / (n - {d})), {digits}) as std_err, round(b{k} / sqrt(v{k} * sse / (n - {d})), 3) as t_stat, round(1 - sse / (syy - sy * sy / n), 6) as r2, cast(n as bigint) as n from f" for k in range(d))
    return f"with s as ({sums_sql(src, d, by)}), c as (select *, {coefs}, {inv} from s), f as (select *, {sse} as sse from c) {rows}"


def newton_sql(src: str, d: int, rounds: int, by: str = "") -> str:
    """CTEs b0 .. b{rounds} of Newton rounds of a logistic fit."""
    key = f"{by}, " if by else ""
    on = f" join b{{i}} using ({by})" if by else ", b{i}"
    eta = " + ".join(f"x{k} * b{k}" for k in range(d))
    start = f"b0 as (select {'distinct ' + key if by else ''}{', '.join(f'0.0::double as b{k}' for k in range(d))}{' from d' if by else ''})"
    ctes = [f"d as ({src})", start]
    g = gram(d)
    for i in range(rounds):
        w = "(1 / (1 + exp(-eta))) * (1 - 1 / (1 + exp(-eta)))"
        cols = [f"sum(x{a} * (y - 1 / (1 + exp(-eta)))) as xy{a}" for a in range(d)] + [f"sum(({w}) * x{a} * x{c}) as g{a}_{c}" for a in range(d) for c in range(a + 1)]
        grp = f"group by {by}, " + ", ".join(f"b{k}" for k in range(d)) if by else "group by " + ", ".join(f"b{k}" for k in range(d))
        ctes.append(f"s{i} as materialized (select {key}{', '.join(f'b{k}' for k in range(d))}, {', '.join(cols)} from (select d.*, {', '.join(f'b{k}' for k in range(d))}, {eta} as eta from d{on.format(i=i)}) {grp})")
        swap = lambda k: [[g[a][j] if j != k else f"xy{a}" for j in range(d)] for a in range(d)]
        ctes.append(f"b{i + 1} as materialized (select {key}{', '.join(f'b{k} + {det(swap(k))} / {det(g)} as b{k}' for k in range(d))} from s{i})")
    return "with " + ", ".join(ctes)
