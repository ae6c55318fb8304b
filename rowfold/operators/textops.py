"""Tokens, features, gram indexes and approximate matching."""

from __future__ import annotations

import math
from collections.abc import Iterator, Sequence
from functools import reduce

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

TOKEN = r"[\p{L}\p{N}@._%+-]*[\p{L}\p{N}]|[^\s\p{L}\p{N}]"


def tokenize(df: DataFrame, id_col: str, text_col: str, pattern: str = r"\S+", most: int | None = None) -> DataFrame:
    """(doc_id, pos, token), places from 0. most: only the first tokens of each text."""
    toks = F.regexp_extract_all(F.col(text_col), F.lit(f"({pattern})"), F.lit(1))
    toks = F.slice(toks, 1, most) if most else toks
    return df.select(F.col(id_col).alias("doc_id"), F.posexplode(toks).alias("pos", "token"))


def terms(df: DataFrame, id_col: str, text_col: str, pattern: str = r"[a-z]+") -> DataFrame:
    return tokenize(df.withColumn("__t", F.lower(text_col)), id_col, "__t", pattern).groupBy("doc_id", F.col("token").alias("term")).agg(F.count("*").alias("cnt"))


def document_terms(df: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """(doc_id, terms, counts): the distinct runs of a-z of each lower-cased text and how often they occur, one row a
    document with a text. Texts stay in their tasks, unless rows share an id: these are one document."""
    src = df.select(F.col(id_col).alias("doc_id"), F.lower(text_col).alias("text"))
    if not src.groupBy("doc_id").agg(F.count("*").alias("n")).filter("n > 1").isEmpty():
        src = src.groupBy("doc_id").agg(F.array_join(F.collect_list("text"), " ").alias("text"))
    kind = dict(src.dtypes)["doc_id"]

    def counted(ids: pa.Array, text: pa.Array) -> pa.RecordBatch:
        text = pc.fill_null(text, "")
        at = np.frombuffer(text.buffers()[1], np.int32)[text.offset : text.offset + len(text) + 1].astype(np.int64)
        data = np.frombuffer(text.buffers()[2] or b"", np.uint8)[at[0] : at[-1]]
        at = at - at[0]
        letter = np.concatenate([(data >= 97) & (data <= 122), [False]])
        new, last = letter.copy(), letter.copy()
        new[1:] &= ~letter[:-1]
        last[:-1] &= ~letter[1:]
        new[at[:-1]], last[at[1:] - 1] = letter[at[:-1]], letter[at[1:] - 1]  # no run goes on into the next row
        start, size = np.flatnonzero(new), np.flatnonzero(last) + 1
        size -= start
        words = pa.StringArray.from_buffers(len(start), pa.py_buffer(np.concatenate([[0], np.cumsum(size)]).astype(np.int32)), pa.py_buffer(data[letter[:-1]])).dictionary_encode()
        every = max(1, len(words.dictionary))
        key, n = np.unique((np.searchsorted(at, start, side="right") - 1) * every + np.asarray(words.indices), return_counts=True)
        row = np.searchsorted(key // every, np.arange(len(text) + 1)).astype(np.int32)
        return pa.RecordBatch.from_arrays([ids, pa.ListArray.from_arrays(row, words.dictionary.take(pa.array(key % every))), pa.ListArray.from_arrays(row, pa.array(n, pa.int32()))], names=["doc_id", "terms", "counts"])

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            part = np.cumsum(np.asarray(pc.fill_null(pc.binary_length(b.column(1)), 0), dtype=np.int64)) >> 22  # about 4 MB at once
            cuts = np.concatenate([[0], np.flatnonzero(np.diff(part)) + 1, [b.num_rows]])
            for a, z in zip(cuts[:-1], cuts[1:]):
                if z > a:
                    yield counted(b.column(0).slice(a, z - a), b.column(1).slice(a, z - a))

    return src.mapInArrow(work, f"doc_id {kind}, terms array<string>, counts array<int>")


def word_blocks(batches: Iterator[pa.RecordBatch], most: int = 1 << 22) -> Iterator[tuple[pa.Array, np.ndarray, np.ndarray, pa.Array]]:
    """(ids, tokens of each document, word of each token, distinct words) of rows (id, text), by about `most` bytes of text or
    one document. Tokens are runs of anything but blanks and line ends; texts without any are left out."""

    def block(ids: pa.Array, text: pa.Array):
        at = np.frombuffer(text.buffers()[1], np.int32)[text.offset : text.offset + len(text) + 1].astype(np.int64)
        data = np.frombuffer(text.buffers()[2] or b"", np.uint8)[at[0] : at[-1]]
        at = at - at[0]
        inner = np.concatenate([~((data == 32) | (data == 10) | (data == 9) | (data == 13)), [False]])
        new, last = inner.copy(), inner.copy()
        new[1:] &= ~inner[:-1]
        last[:-1] &= ~inner[1:]
        full = at[1:] > at[:-1]
        new[at[:-1][full]], last[at[1:][full] - 1] = inner[at[:-1][full]], inner[at[1:][full] - 1]  # no run goes on into the next row
        start, size = np.flatnonzero(new), np.flatnonzero(last) + 1
        size -= start
        words = pa.StringArray.from_buffers(len(start), pa.py_buffer(np.concatenate([[0], np.cumsum(size)]).astype(np.int32)), pa.py_buffer(data[inner[:-1]])).dictionary_encode()
        tokens = np.diff(np.searchsorted(start, at))
        return ids.filter(pa.array(tokens > 0)), tokens[tokens > 0], np.asarray(words.indices), words.dictionary

    for b in batches:
        text = pc.fill_null(b.column(1), "")
        part = np.cumsum(np.asarray(pc.binary_length(text), dtype=np.int64)) // most
        cuts = np.concatenate([[0], np.flatnonzero(np.diff(part)) + 1, [b.num_rows]])
        for a, z in zip(cuts[:-1], cuts[1:]):
            if z > a:
                got = block(b.column(0).slice(a, z - a), text.slice(a, z - a))
                if len(got[1]):
                    yield got


def token_shape(c: Column) -> Column:
    return F.regexp_replace(F.regexp_replace(F.regexp_replace(c, "[A-Z]", "X"), "[a-z]", "x"), "[0-9]", "d")


def strip_html(c: Column) -> Column:
    """Text of a page: scripts and styles go first, then tags; runs of white space become one blank."""
    bare = F.regexp_replace(c, r"(?is)<(script|style)[^>]*>.*?</(script|style)>", " ")
    return F.trim(F.regexp_replace(F.regexp_replace(bare, r"<[^>]*>", " "), r"\s+", " "))


# features: (doc_id, pos, feature, value)


def feat_dictionary(tokens: DataFrame, words: DataFrame, word: str, name: str, most: int = 1_000_000) -> DataFrame:
    """Fires where the lower-cased token is in the dictionary; a dictionary of up to `most` words is broadcast."""
    d = words.select(F.lower(word).alias("w")).distinct()
    d = F.broadcast(d) if d.count() <= most else d
    return tokens.join(d, F.lower("token") == F.col("w"), "left_semi").select("doc_id", "pos", F.lit(name).alias("feature"), F.lit(1.0).alias("value"))


def feat_regex(tokens: DataFrame, patterns: dict[str, str]) -> DataFrame:
    hits = F.filter(F.array(*[F.when(F.col("token").rlike(p), F.lit(n)) for n, p in patterns.items()]), lambda x: x.isNotNull())
    return tokens.select("doc_id", "pos", F.explode(hits).alias("feature"), F.lit(1.0).alias("value"))


def feat_edge(tagged: DataFrame) -> DataFrame:
    """Pairs of a token's tag and the one before it."""
    prev = F.lag("tag").over(Window.partitionBy("doc_id").orderBy("pos"))
    return tagged.withColumn("p", prev).filter("p is not null").select("doc_id", "pos", F.concat_ws(">", "p", "tag").alias("feature"), F.lit(1.0).alias("value"))


def feat_word(tokens: DataFrame, vocabulary: DataFrame) -> DataFrame:
    """Fires for tokens seen in training. The vocabulary grows with the corpus, so this is an equi-join; hot tokens are
    left to the engine's skew handling."""
    v = vocabulary.select(F.lower("token").alias("w")).distinct()
    return tokens.join(v, F.lower("token") == F.col("w")).select("doc_id", "pos", F.concat(F.lit("w="), F.col("w")).alias("feature"), F.lit(1.0).alias("value"))


def feat_position(tokens: DataFrame) -> DataFrame:
    last = F.max("pos").over(Window.partitionBy("doc_id"))
    at = tokens.withColumn("last", last)
    hits = F.filter(F.array(F.when(F.col("pos") == 0, F.lit("first")), F.when(F.col("pos") == F.col("last"), F.lit("final"))), lambda x: x.isNotNull())
    return at.select("doc_id", "pos", F.explode(hits).alias("feature"), F.lit(1.0).alias("value"))


def extract_features(tokens: DataFrame, regexes: dict[str, str] | None = None, dictionaries: dict[str, tuple[DataFrame, str]] | None = None, vocabulary: DataFrame | None = None, position: bool = True) -> DataFrame:
    parts = [feat_regex(tokens, regexes)] if regexes else []
    parts += [feat_dictionary(tokens, d, w, n) for n, (d, w) in (dictionaries or {}).items()]
    parts += [feat_word(tokens, vocabulary)] if vocabulary is not None else []
    parts += [feat_position(tokens)] if position else []
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def feature_ids(features: DataFrame) -> DataFrame:
    """(feature, feature_id): a stable number for each feature, from its name alone."""
    return features.select("feature").distinct().withColumn("feature_id", F.xxhash64("feature"))


# grams


def qgrams(c: Column, q: int = 3, pad: bool = False, lower: bool = True) -> Column:
    """All substrings of q characters in order; padded, each word gets q - 1 blanks before and one after."""
    s = F.lower(c) if lower else c
    # looking ahead from every place is one pass over the text; a substring by its place would count from the start each time
    one = lambda w: F.regexp_extract_all(w, F.lit(rf"(?s)(?![\uDC00-\uDFFF])(?=(.{{{q}}}))"), F.lit(1))
    if not pad:
        return one(s)
    words = F.filter(F.split(s, r"[^\p{L}\p{N}]+"), lambda w: w != "")
    return F.flatten(F.transform(words, lambda w: one(F.concat(F.lit(" " * (q - 1)), w, F.lit(" ")))))


def gram_similarity(a: Column, b: Column) -> Column:
    """Jaccard similarity of two gram arrays."""
    return F.try_divide(F.size(F.array_intersect(a, b)), F.size(F.array_union(a, b)))


def gram_dice(a: Column, b: Column) -> Column:
    """Dice coefficient of two gram arrays."""
    return F.try_divide(2 * F.size(F.array_intersect(a, b)), F.size(F.array_distinct(a)) + F.size(F.array_distinct(b)))


def within_edits(a: Column, b: Column, most: int) -> Column:
    """Whether two strings are at most `most` edits apart; the length alone decides where it can."""
    return (F.abs(F.length(a) - F.length(b)) <= most) & (F.levenshtein(a, b, most) >= 0)


def build_qgram_index(df: DataFrame, id_col: str, text_col: str, q: int = 3) -> DataFrame:
    """(gram, doc_id): distinct within a text before anything is shuffled. Save it clustered by gram to prune reads."""
    return df.select(F.col(id_col).alias("doc_id"), F.explode(F.array_distinct(qgrams(F.col(text_col), q))).alias("gram")).select("gram", "doc_id")


def _window_best(text: str, grams: frozenset, q: int, sizes: tuple[int, ...], need: int) -> float:
    """The best similarity of a text's windows of some numbers of words with a query's grams, or 0 where no window shares
    `need` of them. Windows are of words parted by one blank, lower-cased."""
    words = text.lower().split()
    t = " ".join(words)
    n = len(t) - q + 1
    if n <= 0 or not words:
        return 0.0
    upto = np.zeros(n + 1, np.int32)  # places of the query's grams, of which a window holds no fewer than distinct ones
    np.cumsum(np.fromiter((t[i : i + q] in grams for i in range(n)), bool, n), out=upto[1:])
    length = np.fromiter(map(len, words), np.int64, len(words))
    start = np.cumsum(length + 1) - length - 1
    best, seen = 0.0, set()
    for k in sizes:
        k = min(k, len(words))
        if k in seen:
            continue
        seen.add(k)
        a = start[: len(words) - k + 1]
        z = np.maximum(start[k - 1 :] + length[k - 1 :] - q + 1, a)
        for i in np.flatnonzero(upto[np.minimum(z, n)] - upto[np.minimum(a, n)] >= need).tolist():
            own = {t[j : j + q] for j in range(int(a[i]), int(z[i]))}
            shared = len(own & grams)
            best = max(best, shared / (len(own) + len(grams) - shared))
    return best


def approx_match(df: DataFrame, id_col: str, text_col: str, query: str, threshold: float = 0.3, scope: str = "document", q: int = 3) -> DataFrame:
    """(doc_id, similarity) of texts that match the query approximately. document: similarity of the whole gram sets;
    window: the best of all windows of as many words as the query has, give or take one. Candidates share enough grams;
    only windows with enough of them are compared."""
    grams = sorted({query.lower()[i : i + q] for i in range(len(query) - q + 1)})
    lit = F.array(*map(F.lit, grams)) if grams else F.array().cast("array<string>")
    src = df.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("t"))
    if scope == "document":
        s = src.withColumn("g", F.array_distinct(qgrams(F.col("t"), q))).withColumn("shared", F.size(F.array_intersect("g", lit)))
        need = F.ceil(threshold * (F.size("g") + len(grams)) / (1 + threshold))
        return s.filter(F.col("shared") >= need).select("doc_id", gram_similarity(F.col("g"), lit).alias("similarity")).filter(F.col("similarity") >= threshold)
    k = len(query.split())
    least, sizes = math.ceil(threshold * len(grams)), tuple(n for n in (k - 1, k, k + 1) if n > 0)
    low = F.lower("t")
    held = reduce(lambda a, b: a + b, [low.contains(g).cast("int") for g in grams if " " not in g], F.lit(0))  # without blanks, whose runs a window shortens
    cand = src.filter(F.col("t").isNotNull() & (held >= least - sum(" " in g for g in grams)))
    wanted = frozenset(grams)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            best = [_window_best(t, wanted, q, sizes, max(1, least)) for t in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(best, pa.float64())], names=["doc_id", "similarity"])

    return cand.mapInArrow(work, f"doc_id {dict(cand.dtypes)['doc_id']}, similarity double").filter(F.col("similarity") >= threshold)


def approx_join(left: DataFrame, right: DataFrame, left_id: str, left_text: str, right_id: str, right_text: str, threshold: float, q: int = 3) -> DataFrame:
    """(left_id, right_id, similarity) of pairs whose gram sets reach the threshold. Only the rarest grams of a set, as
    many as a match cannot miss, are joined; then sizes, then the sets decide."""
    sets = lambda df, i, t, side: df.select(F.col(i).alias(f"{side}_id"), F.array_distinct(qgrams(F.col(t), q)).alias(f"{side}_g")).filter(F.size(f"{side}_g") > 0)
    a, b = sets(left, left_id, left_text, "left"), sets(right, right_id, right_text, "right")
    freq = a.select(F.explode("left_g").alias("gram")).unionByName(b.select(F.explode("right_g").alias("gram"))).groupBy("gram").agg(F.count("*").alias("f"))

    def prefix(df: DataFrame, side: str) -> DataFrame:
        each = df.select(f"{side}_id", F.size(f"{side}_g").alias("n"), F.explode(f"{side}_g").alias("gram")).join(freq, "gram")
        rank = F.row_number().over(Window.partitionBy(f"{side}_id").orderBy("f", "gram"))
        return each.withColumn("r", rank).filter(F.col("r") <= F.col("n") - F.ceil(threshold * F.col("n")) + 1).select("gram", f"{side}_id", F.col("n").alias(f"{side}_n"))

    pairs = prefix(a, "left").join(prefix(b, "right"), "gram").filter((F.col("left_n") >= threshold * F.col("right_n")) & (F.col("right_n") >= threshold * F.col("left_n"))).select("left_id", "right_id").distinct()
    both = pairs.join(a, "left_id").join(b, "right_id")
    return both.select("left_id", "right_id", gram_similarity(F.col("left_g"), F.col("right_g")).alias("similarity")).filter(F.col("similarity") >= threshold)


def contained_passages(docs: DataFrame, passages: DataFrame, doc_id: str, text: str, item_id: str, passage: str, share: float = 0.9, q: int = 3) -> DataFrame:
    """(doc_id, item_id, share) of documents that hold at least `share` of a passage's distinct grams in common."""
    p = passages.select(F.col(item_id).alias("item_id"), F.array_distinct(qgrams(F.col(passage), q)).alias("g")).filter(F.size("g") > 0)
    own = p.select("item_id", F.size("g").alias("n"), F.explode("g").alias("gram"))
    idx = build_qgram_index(docs, doc_id, text, q)
    hits = idx.join(own, "gram").groupBy("doc_id", "item_id").agg((F.count("*") / F.max("n")).alias("share"))
    return hits.filter(F.col("share") >= share)


def build_term_index(tokens: DataFrame) -> DataFrame:
    """Postings (term, doc_id, positions): each posting is of one document, so no term's list meets in one row."""
    return tokens.groupBy(F.lower("token").alias("term"), "doc_id").agg(F.sort_array(F.collect_list("pos")).alias("positions"))


def lookup_terms(index: DataFrame, words: Sequence[str], mode: str = "and") -> DataFrame:
    """(doc_id, hits) of the documents that hold all, or any, of the words."""
    words = sorted({w.lower() for w in words})
    hit = index.filter(F.col("term").isin(words)).groupBy("doc_id").agg(F.count("*").alias("hits"))
    return hit.filter(F.col("hits") == len(words)) if mode == "and" else hit
