"""Quality classifier: perplexity under a Kneser-Ney model of trusted text, and the odds of toxic words.

The model is in kneser_ney: its counts are sharded tables that documents meet by
joins. Every document's perplexity is held against quantiles of the trusted
documents' own perplexities in its language and length class, drawn in to where
labelled bad documents begin; a trusted document is scored as if the n-grams that
only it holds were unseen. A few toxic words hardly move a perplexity, so the
words that many toxic texts and few trusted ones hold give a second score.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from rowfold.llm.common import slices, staged, steady
from rowfold.llm.kneser_ney import SLICE, gram_counts, kneser_ney, score


def trusted(docs: DataFrame, labels: DataFrame, most: int = 2_000_000) -> DataFrame:
    """docs with `sure`, that a label calls the document good, and no label bad or toxic, and with `bad` and `toxic`, that
    some label says so. The ids of a label table of up to `most` rows are broadcast; a larger one is joined by shuffle, and
    the result staged, since a shuffle gives rows in no stable order."""
    good = labels.filter("doc_id is not null").groupBy("doc_id").agg(F.min("quality").alias("q"), F.max("toxic").alias("t")).selectExpr("doc_id", "q = 1 and coalesce(t, 0) = 0 as sure", "q = 0 as bad", "t = 1 as toxic")
    small = labels.count() <= most
    out = docs.join(F.broadcast(good) if small else good, "doc_id", "left").withColumns({k: F.coalesce(k, F.lit(False)) for k in ("sure", "bad", "toxic")})
    return out if small else staged(out, "quality-labelled")


def quantiles(scored: DataFrame, low: float, high: float, by: str = "lang") -> DataFrame:
    """(lang, lo, hi, n_ref): quantiles of the perplexities of all rows, in steps of half a per cent, by running counts over
    the distinct values: at most some 2,800 a group, whatever its rows."""
    value = F.round(F.exp(F.round(F.log("perplexity") * 200) / 200), 3)
    bins = scored.filter("perplexity is not null").groupBy(by, value.alias("v")).agg(F.count("*").alias("n"))
    w = Window.partitionBy(by).orderBy("v")
    total = Window.partitionBy(by)
    run = bins.withColumn("upto", F.sum("n").over(w)).withColumn("all", F.sum("n").over(total))
    return run.groupBy(by).agg(F.min(F.when(F.col("upto") >= F.lit(low) * F.col("all"), F.col("v"))).alias("lo"), F.min(F.when(F.col("upto") >= F.lit(high) * F.col("all"), F.col("v"))).alias("hi"), F.max("all").alias("n_ref"))


def words_of(texts: pa.Array) -> tuple[pa.Array, np.ndarray]:
    """(words, text): lower-case runs of letters and digits of all texts, and the text of each."""
    lists = pc.split_pattern_regex(pc.utf8_lower(pc.fill_null(texts, "")), r"[^\p{L}\p{N}]+")
    return lists.flatten(), pc.list_parent_indices(lists).to_numpy()


def texts_with(texts: DataFrame, only: list[str] | None = None, text_col: str = "text") -> DataFrame:
    """(word, n): in how many texts a word stands, for all words or those given; tasks add up their own."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches, 0, SLICE):
            word, text = words_of(b.column(0))
            t = pa.table({"word": word, "text": text})
            if only is not None:
                t = t.filter(pc.is_in(word, pa.array(only, pa.string())))
            n = t.filter(pc.not_equal(t["word"], "")).group_by(["word", "text"]).aggregate([]).group_by("word").aggregate([("text", "count")])
            yield pa.RecordBatch.from_arrays([n["word"].combine_chunks().cast(pa.string()), n["text_count"].combine_chunks()], names=["word", "n"])

    return texts.select(text_col).mapInArrow(count, "word string, n long").groupBy("word").agg(F.sum("n").alias("n"))


def toxic_words(rows: DataFrame, share: float, odds: float) -> tuple[list[tuple[str, int, int]], int, int]:
    """((word, toxic texts, trusted texts) of toxic words, number of toxic texts, of trusted texts).

    A toxic word stands in at least two and the given share of the toxic texts, which bounds their number by the
    mean number of words of a toxic text over the share; its odds of toxic against trusted texts are at least `odds`."""
    n = rows.agg(F.sum(F.col("toxic").cast("long")).alias("t"), F.sum(F.col("sure").cast("long")).alias("g")).first()
    nt, ng = n["t"] or 0, n["g"] or 0
    often = {r["word"]: r["n"] for r in texts_with(rows.filter("toxic")).filter(F.col("n") >= max(2, share * nt)).collect()} if nt else {}
    good = {r["word"]: r["n"] for r in texts_with(rows.filter("sure"), sorted(often)).collect()} if often and ng else {}
    out = [(w, t, good.get(w, 0)) for w, t in sorted(often.items())]
    return [x for x in out if (x[1] + 0.5) * (ng + 1) >= odds * (x[2] + 0.5) * (nt + 1)], nt, ng


def word_odds(words: list[tuple[str, int, int]], nt: int, ng: int):
    """A function of (texts, rows) that gives each text the greatest log odds of its toxic words, or 0. A labelled text does
    not count for its own words; two others must hold a word."""
    known = [w for w, _, _ in words]
    t_all, g_all = (np.array([x[i] for x in words], np.float64) for i in (1, 2))

    def of(texts: pa.Array, rows: pa.RecordBatch) -> pa.Array:
        out = np.zeros(len(texts))
        if known:
            word, text = words_of(texts)
            at = pc.index_in(word, pa.array(known, pa.string()))
            hit = pc.is_valid(at).to_numpy(zero_copy_only=False)
            k, text = at.drop_null().to_numpy(), text[hit]
            own = {c: rows.column(rows.schema.get_field_index(c)).to_numpy(zero_copy_only=False).astype(np.float64)[text] for c in ("toxic", "sure")}
            t, g = t_all[k] - own["toxic"], g_all[k] - own["sure"]
            np.maximum.at(out, text, np.where(t >= 2, np.log((t + 0.5) / (nt + 1)) - np.log((g + 0.5) / (ng + 1)), 0.0))
        return pa.array(np.round(out, 2))

    return of


def length_class(n: Column) -> Column:
    """Classes of length by powers of four, up to 4096 symbols and more."""
    return F.least(F.lit(6), F.floor(F.log(F.greatest(n, F.lit(1)).cast("double")) / F.log(F.lit(4.0)) + 1e-9)).cast("int")


def cuts_of(scored: DataFrame, low: float, high: float, slack: float, most_keys: int = 100_000) -> DataFrame:
    """(key, lo, hi, n_ref): the quantiles of the trusted rows of each key, widened by slack and by the uncertainty of a
    quantile of few rows (1 over the root of their number), but not past the nearest bad row."""
    q = staged(quantiles(scored.filter("sure"), low, high, "key"), "quality-quantiles")
    small = F.broadcast(q) if q.count() <= most_keys else q  # one row a language and length class
    bad = scored.filter("bad and perplexity is not null").select("key", "perplexity").join(small, "key")
    near = bad.groupBy("key").agg(F.max(F.when(F.col("perplexity") < F.col("lo"), F.col("perplexity"))).alias("under"), F.min(F.when(F.col("perplexity") > F.col("hi"), F.col("perplexity"))).alias("over"))
    wide = slack * (1 + 1 / F.sqrt("n_ref"))
    lo, hi = F.col("lo") / wide, F.col("hi") * wide
    return q.join(near, "key", "left").select("key", F.greatest(lo, F.least("lo", F.coalesce(F.col("under") + 0.001, lo))).alias("lo"), F.least(hi, F.greatest("hi", F.coalesce(F.col("over") - 0.001, hi))).alias("hi"), "n_ref")


def toxic_cuts(scored: DataFrame) -> DataFrame:
    """(key, cut, n_ref): beyond which toxicity the caught share of toxic rows most exceeds the lost share of trusted ones."""
    bins = scored.groupBy("key", F.col("toxicity").alias("v")).agg(F.sum(F.col("sure").cast("long")).alias("g"), F.sum(F.col("toxic").cast("long")).alias("t"))
    upto, total = Window.partitionBy("key").orderBy("v"), Window.partitionBy("key")
    share = {k: F.sum(k).over(upto) / F.sum(k).over(total) for k in ("g", "t")}
    run = bins.filter("g + t > 0").withColumns({"n_ref": F.least(F.sum("g").over(total), F.sum("t").over(total))})
    run = run.filter("n_ref > 0").withColumn("gain", share["g"] - share["t"])
    return run.groupBy("key").agg(F.max_by("v", F.struct("gain", "v")).alias("cut"), F.max("n_ref").alias("n_ref"))


def classify(docs: DataFrame, labels: DataFrame, low: float = 0.001, high: float = 0.995, slack: float = 1.05, least: int = 50, toxic_share: float = 0.002, toxic_odds: float = 4.0, carry: tuple[str, ...] = ()) -> DataFrame:
    """One row per input row: doc_id, lang, n_symbols, perplexity, lo, hi, toxicity, toxic_cut, keep, and the columns to carry.

    The model is trained on all trusted documents. A document is kept if its perplexity lies between the `low` and
    `high` quantiles of the trusted documents in its language and length class, widened on both sides by the factor
    `slack`, more for few documents, or up to the nearest labelled bad document, and if its toxicity is not beyond the cut that best parts the
    labelled toxic from the trusted documents of its language. A class with fewer than `least` trusted documents uses
    the cuts of its language, such a language those of all. toxic_share and toxic_odds: what makes a word toxic.
    Rejected are null and empty texts; a null language is a language of its own. Without any trusted document,
    everything with text is kept. Null or repeated ids keep their rows, and rows of one id its label; an empty table gives none;
    further columns are ignored. n-grams of one shard with equal 64-bit keys, found by chance only, share a probability.
    """
    src = trusted(steady(docs.select("doc_id", "lang", "text", *carry), "quality-input"), labels)
    model = kneser_ney(gram_counts(src.filter("sure")))
    scored = score(src, model, word_odds(*toxic_words(src, toxic_share, toxic_odds))).withColumnRenamed("extra", "toxicity")
    own = F.coalesce("lang", F.lit("?"))
    scored = staged(scored.withColumns({"_lang": F.concat(own, F.lit("/")), "_class": F.concat(own, F.lit("/"), length_class(F.col("n_symbols")).cast("string"))}), "quality-scores")
    labelled = scored.filter("sure or bad or toxic").select("_class", "_lang", "perplexity", "toxicity", "sure", "bad", "toxic")
    keyed = labelled.withColumn("key", F.explode(F.array("_class", "_lang", F.lit("*"))))
    cuts = staged(cuts_of(keyed, low, high, slack).filter((F.col("n_ref") >= least) | (F.col("key") == "*")).select("key", "lo", "hi"), "quality-cuts")
    tox = staged(toxic_cuts(keyed.filter("key like '%/' or key = '*'")).filter((F.col("n_ref") >= least) | (F.col("key") == "*")).select("key", "cut"), "quality-toxic-cuts")
    for name, table, key, cols in (("own", cuts, "_class", ("lo", "hi")), ("lang", cuts, "_lang", ("lo", "hi")), ("all", cuts, F.lit("*"), ("lo", "hi")), ("lang", tox, "_lang", ("cut",)), ("all", tox, F.lit("*"), ("cut",))):
        col = F.col(key) if isinstance(key, str) else key
        scored = scored.join(table.select(F.col("key").alias("_key"), *(F.col(c).alias(f"{name}_{c}") for c in cols)), col == F.col("_key"), "left").drop("_key")
    first = lambda c, names, none: F.round(F.coalesce(*(F.col(f"{n}_{c}") for n in names), F.lit(none)), 3)
    cut = scored.withColumns({"lo": first("lo", ("own", "lang", "all"), 0.0), "hi": first("hi", ("own", "lang", "all"), float("inf")), "toxic_cut": first("cut", ("lang", "all"), float("inf"))})
    keep = F.coalesce(F.col("perplexity").between(F.col("lo"), F.col("hi")) & (F.col("toxicity") <= F.col("toxic_cut")), F.lit(False))
    return cut.select("doc_id", "lang", "n_symbols", "perplexity", "lo", "hi", "toxicity", "toxic_cut", keep.alias("keep"), *carry)
