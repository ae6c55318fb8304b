"""Interpolated modified Kneser-Ney model of code points, its counts sharded by n-gram.

An n-gram of at most five code points is a pair of long numbers, 21 bits a point.
The counts of every length, what they leave to shorter contexts and which n-grams
one text alone holds make one table, dealt by n-gram; it grows with the trusted
text and is never gathered. Documents are put into blocks of bounded size. A block
asks every shard for its distinct n-grams of all lengths, shards answer in the
order asked, and the answers meet the block's texts, where probabilities are
interpolated from the shortest n-grams up. Texts move once, compressed.
"""

from __future__ import annotations

import hashlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rowfold.llm.common import slices, staged
from rowfold.llm.shingles import U, mix

ORDER = 5
START = 0x10FFFF  # no character; stands ORDER - 1 times before a text
POINTS = 0x110000
SLICE = 2 << 20  # bytes of text, or a single text
WINDOW = 2 << 20  # code points looked at together
BLOCK = 16 << 20  # bytes of text that share their questions
PRIME = 2147483647
SHARD_ROWS = 1 << 20  # rows of the model in a shard
LOW, MID = (1 << 21) - 1, (1 << 42) - 1
CODEC = pa.Codec("zstd", compression_level=3)


def windows(texts: pa.Array) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """(hi, lo, at, text) of stretches of the texts: the distinct ORDER-grams that end in one, which of them ends at each
    code point, and each code point's text."""
    points = np.frombuffer("".join(x or "" for x in texts.to_pylist()).encode("utf-32-le"), np.uint32)
    size = pc.fill_null(pc.utf8_length(texts), 0).to_numpy(zero_copy_only=False).astype(np.int64)
    text = np.repeat(np.arange(len(size), dtype=np.int32), size)
    begin = np.repeat(np.cumsum(size) - size, ORDER - 1)
    line = np.insert(points, begin, START)
    real = np.insert(np.ones(len(points), bool), begin, False)
    done = 0
    for a in range(0, max(0, len(line) - ORDER + 1), WINDOW):
        own, good = line[a : a + WINDOW + ORDER - 1], real[a + ORDER - 1 : a + ORDER - 1 + WINDOW]
        present = np.zeros(POINTS, bool)
        present[own] = True
        alphabet = np.flatnonzero(present)
        sym = (np.cumsum(present) - 1)[own]
        n, base = len(good), len(alphabet)
        ident, bound = sym[:n].copy(), base
        for i in range(1, ORDER):
            if bound * base >= 1 << 63:
                d = pa.array(ident).dictionary_encode()
                ident, bound = d.indices.to_numpy().astype(np.int64), len(d.dictionary)
            ident *= base
            ident += sym[i : i + n]
            bound *= base
        d = pa.array(ident[good]).dictionary_encode()
        at = d.indices.to_numpy()
        first = np.zeros(len(d.dictionary), np.int64)
        first[at[::-1]] = np.flatnonzero(good)[::-1]
        s = [alphabet[sym[first + i]] for i in range(ORDER)]
        yield s[0] << 42 | s[1] << 21 | s[2], s[3] << 21 | s[4], at, text[done : done + len(at)]
        done += len(at)


def distinct(hi: np.ndarray, lo: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(hi, lo, inverse) of the distinct pairs, in order."""
    order = np.lexsort((lo, hi)) if lo.any() else np.argsort(hi, kind="stable")
    h, w = hi[order], lo[order]
    new = np.ones(len(h), bool)
    new[1:] = (h[1:] != h[:-1]) | (w[1:] != w[:-1])
    inverse = np.empty(len(h), np.int64)
    inverse[order] = np.cumsum(new) - 1
    return h[new], w[new], inverse


def suffix(hi: np.ndarray, lo: np.ndarray, m: int) -> tuple[np.ndarray, np.ndarray]:
    """m-grams without their first code point."""
    if m == 5:
        return (hi & MID) << 21 | lo >> 21, lo & LOW
    none = np.zeros_like(lo)
    return ((hi & MID) << 21 | lo if m == 4 else hi & (MID, LOW, 0)[3 - m]), none


def context(hi: np.ndarray, lo: np.ndarray, m: int) -> tuple[np.ndarray, np.ndarray]:
    """m-grams without their last code point."""
    return (hi, lo >> 21) if m == 5 else (hi if m == 4 else hi >> 21, np.zeros_like(lo))


def suffix_sql(m: int) -> list[Column]:
    hi = {5: f"shiftleft(hi & {MID}L, 21) | shiftright(lo, 21)", 4: f"shiftleft(hi & {MID}L, 21) | lo", 3: f"hi & {MID}L", 2: f"hi & {LOW}L"}[m]
    return [F.expr(hi).alias("hi"), F.expr(f"lo & {LOW}L" if m == 5 else "0L").alias("lo")]


def context_sql(m: int) -> list[Column]:
    return [F.expr("hi" if m >= 4 else "shiftright(hi, 21)" if m > 1 else "0L").alias("hi"), F.expr("shiftright(lo, 21)" if m == 5 else "0L").alias("lo")]


def shard(hi: np.ndarray, lo: np.ndarray, m, parts: int) -> np.ndarray:
    return ((hi % PRIME * 48271 + lo % PRIME * 69621 + np.int64(16807) * m) % PRIME % parts).astype(np.int32)


def shard_sql(parts: int) -> Column:
    return F.expr(f"cast((hi % {PRIME} * 48271 + lo % {PRIME} * 69621 + 16807L * m) % {PRIME} % {parts} as int)")


def chain(hi: np.ndarray, lo: np.ndarray) -> list[tuple[np.ndarray, ...]]:
    """By length from ORDER to 0 (hi, lo, suffix, context): the distinct n-grams that the probabilities of those given
    rest on, and for each the places of its suffix and its context one length below."""
    out = []
    for m in range(ORDER, 0, -1):
        s, c = suffix(hi, lo, m), context(hi, lo, m)
        n = len(hi)
        h, w, inverse = distinct(np.concatenate([s[0], c[0]]), np.concatenate([s[1], c[1]]))
        out.append((hi, lo, inverse[:n], inverse[n:]))
        hi, lo = h, w
    return [*out, (hi, lo, None, None)]


def _planes(x: np.ndarray) -> bytes:
    """Byte by byte of all numbers: equal bytes lie together and compress."""
    return np.ascontiguousarray(x.view(np.uint8).reshape(len(x), x.itemsize).T).tobytes()


def _unplanes(raw: np.ndarray, kind: str, n: int) -> np.ndarray:
    size = np.dtype(kind).itemsize
    return np.ascontiguousarray(raw[: n * size].reshape(size, n).T).view(kind).reshape(-1)


def _squeeze(raw: bytes) -> bytes:
    return np.int64(len(raw)).tobytes() + CODEC.compress(raw, asbytes=True)


def _unsqueeze(blob) -> np.ndarray:
    blob = memoryview(blob)
    return np.frombuffer(CODEC.decompress(blob[8:], int(np.frombuffer(blob[:8], "<i8")[0])), np.uint8)


def pack_grams(counts: np.ndarray, hi: np.ndarray, lo: np.ndarray, *more: np.ndarray) -> bytes:
    """n-grams, sorted within each length, `counts` of each length, and 32-bit columns beside them."""
    return _squeeze(b"".join([counts.astype("<i8").tobytes(), _planes(np.diff(hi, prepend=0)), _planes(lo), *(_planes(x.astype("<i4")) for x in more)]))


def unpack_grams(blob, lengths: int, columns: int = 0) -> tuple[np.ndarray, ...]:
    raw = _unsqueeze(blob)
    counts = raw[: 8 * lengths].copy().view("<i8")
    n, raw = int(counts.sum()), raw[8 * lengths :]
    hi, lo = np.cumsum(_unplanes(raw, "<i8", n)), _unplanes(raw[8 * n :], "<i8", n)
    return counts, hi, lo, *(_unplanes(raw[16 * n + 4 * n * k :], "<i4", n) for k in range(columns))


def _grams_of(batches: Iterator[pa.RecordBatch], most: int = 1 << 21) -> Iterator[tuple[np.ndarray, ...]]:
    """(hi, lo, n, who) over texts: distinct ORDER-grams, how often, and the one text that holds each (0: several)."""
    row, held = TaskContext.get().partitionId() * 1_000_003 + 1, []

    def merged() -> tuple[np.ndarray, ...]:
        h, w, n, who = (np.concatenate(x) for x in zip(*held))
        hi, lo, inverse = distinct(h, w)
        least, top = np.full(len(hi), PRIME), np.full(len(hi), -1)
        np.minimum.at(least, inverse, who)
        np.maximum.at(top, inverse, who)
        return hi, lo, np.bincount(inverse, n, len(hi)).astype(np.int64), np.where(least == top, least, 0)

    for b in slices(batches, 0, SLICE):
        for hi, lo, at, text in windows(b.column(0)):
            first, last = np.zeros(len(hi), np.int64), np.zeros(len(hi), np.int64)
            first[at[::-1]], last[at] = text[::-1], text
            held.append((hi, lo, np.bincount(at, minlength=len(hi)), np.where(first == last, (row + first) % (PRIME - 1) + 1, 0)))
        row += b.num_rows
        if sum(len(x[0]) for x in held) > most:
            held = [merged()]
            if len(held[0][0]) > most // 2:
                yield held.pop()
    if held:
        yield merged()


def gram_counts(texts: DataFrame, text_col: str = "text") -> DataFrame:
    """(hi, lo, n, who) over all texts. Tasks add up their own counts and send them by shard, packed."""
    parts = int(texts.sparkSession.conf.get("spark.sql.shuffle.partitions"))

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for hi, lo, n, who in _grams_of(batches):
            part = shard(hi, lo, ORDER, parts)
            order = np.argsort(part, kind="stable")
            edge = np.searchsorted(part[order], np.arange(parts + 1))
            hi, lo, n, who = (x[order] for x in (hi, lo, n, who))
            own = np.flatnonzero(np.diff(edge))
            cut = [slice(edge[p], edge[p + 1]) for p in own]
            big = np.minimum(n, PRIME)  # of a task's two million n-grams
            data = [pack_grams(np.array([s.stop - s.start]), hi[s], lo[s], big[s], who[s]) for s in cut]
            yield pa.RecordBatch.from_arrays([pa.array(own, pa.int32()), pa.array(data, pa.binary())], names=["part", "data"])

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, held = None, []

        def merged() -> list[np.ndarray]:
            h, w, n, who = (np.concatenate(x) for x in zip(*held))
            hi, lo, inverse = distinct(h, w)
            least, top = np.full(len(hi), PRIME), np.full(len(hi), -1)
            np.minimum.at(least, inverse, who)
            np.maximum.at(top, inverse, who)
            total = np.zeros(len(hi), np.int64)
            np.add.at(total, inverse, n)
            return [hi, lo, total, np.where(least == top, least, 0)]

        def rows() -> Iterator[pa.RecordBatch]:
            cols = merged()
            for i in range(0, len(cols[0]), 100_000):
                yield pa.RecordBatch.from_arrays([pa.array(c[i : i + 100_000]) for c in cols], names=["hi", "lo", "n", "who"])

        for b in batches:
            for p, data in zip(b.column(0).to_pylist(), b.column(1)):
                if held and p != now:
                    yield from rows()
                    held = []
                now = p
                held.append([x.astype(np.int64) for x in unpack_grams(data.as_buffer(), 1, 2)[1:]])
                if len(held) > 1 and sum(len(x[0]) for x in held) > max(1 << 21, 3 * len(held[0][0])):
                    held = [merged()]
        if held:
            yield from rows()

    sent = texts.select(text_col).mapInArrow(count, "part int, data binary").repartition(parts, "part").sortWithinPartitions("part")
    return sent.mapInArrow(add, "hi long, lo long, n long, who long")


def kneser_ney(counts: DataFrame) -> DataFrame:
    """(m, hi, lo, a, g, sole): by m-gram either the share a that its own count gives it, with whether one text alone
    holds it, or, as a context, the weight g that its shorter suffix gets.

    Discounts of 1, 2 and 3 or more follow from the counts of counts of each length. The longest n-grams use counts,
    shorter ones the number of distinct code points before.
    """
    levels, out = {ORDER: staged(counts, "kn-counts")}, None
    for m in range(ORDER - 1, 0, -1):
        up = levels[m + 1].select(*suffix_sql(m + 1), "who").groupBy("hi", "lo")
        levels[m] = staged(up.agg(F.count("*").alias("n"), F.when(F.min("who") == F.max("who"), F.min("who")).otherwise(0).cast("long").alias("who")), f"kn-counts{m}")
    for m in range(1, ORDER + 1):
        c = levels[m]
        t = {r["k"]: r["t"] for r in c.filter("n <= 4").groupBy(F.col("n").alias("k")).agg(F.count("*").alias("t")).collect()}  # at most four rows
        t1, t2, t3, t4 = (t.get(k, 0) for k in (1, 2, 3, 4))
        y = t1 / (t1 + 2 * t2) if t1 and t2 else 0.5
        d1, d2, d3 = (min(max(d, 0.05), cap) for d, cap in ((1 - 2 * y * t2 / t1 if t1 else 0.5, 0.95), (2 - 3 * y * t3 / t2 if t2 else 1.0, 1.9), (3 - 4 * y * t4 / t3 if t3 else 1.5, 2.9)))
        cut = F.when(F.col("n") == 1, d1).when(F.col("n") == 2, d2).otherwise(d3)
        own = c.select("hi", "lo", "n", "who", cut.alias("cut"), *(x.alias(f"c{i}") for i, x in enumerate(context_sql(m))))
        totals = own.groupBy("c0", "c1").agg(F.sum("n").alias("total"), F.sum("cut").alias("left"))
        seen = own.join(totals, ["c0", "c1"]).select(F.lit(m).alias("m"), "hi", "lo", ((F.col("n") - F.col("cut")) / F.col("total")).alias("a"), F.lit(None).cast("double").alias("g"), (F.col("who") > 0).alias("sole"))
        left = totals.select(F.lit(m - 1).alias("m"), F.col("c0").alias("hi"), F.col("c1").alias("lo"), F.lit(None).cast("double").alias("a"), (F.col("left") / F.col("total")).alias("g"), F.lit(False).alias("sole"))
        out = seen.unionByName(left) if out is None else out.unionByName(seen).unionByName(left)
    return staged(out, "kn-model")


class _Shard:
    """Rows of the model of one shard, found by n-gram."""

    def __init__(self, rows: list[pa.RecordBatch]):
        t = pa.Table.from_batches(rows)
        m, hi, lo = (t["m"].to_numpy().astype(np.int64), t["hi"].to_numpy(), t["lo"].to_numpy())
        of_seen = pc.is_valid(t["a"]).to_numpy()
        self.tables = []
        for own, values in ((of_seen, ("a", "sole")), (~of_seen, ("g",))):
            h, w = hi[own], lo[own]
            key = self.key(m[own], h, w)
            order = np.argsort(key)
            self.tables.append((key[order], h[order], w[order], [t[v].to_numpy()[own][order] for v in values]))

    @staticmethod
    def key(m: np.ndarray, hi: np.ndarray, lo: np.ndarray) -> np.ndarray:
        return mix(mix(hi.view(U) + m.astype(U)) ^ (lo.view(U) * U(0x9E3779B97F4A7C15)))

    def find(self, kind: int, m: np.ndarray, hi: np.ndarray, lo: np.ndarray) -> tuple[np.ndarray, np.ndarray, list[np.ndarray]]:
        """(found, place, columns)"""
        key, h, w, values = self.tables[kind]
        if not len(key):
            return np.zeros(len(m), bool), np.zeros(len(m), np.int64), [np.zeros(1)] * len(values)
        at = np.minimum(np.searchsorted(key, want := self.key(m, hi, lo)), len(key) - 1)
        return (key[at] == want) & (h[at] == hi) & (w[at] == lo), at, values


def _answer(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows (part, kind, m, hi, lo, a, g, sole, block, data) by part, the model (kind 0) before questions (kind 1), to
    (block, part, data) with the answers in the order asked."""
    now, model, rows = None, None, []
    for b in batches:
        part, kind = b.column(0).to_numpy(), b.column(1).to_numpy()
        cut = np.flatnonzero((np.diff(part) != 0) | (np.diff(kind) != 0)) + 1
        for i, z in zip([0, *cut.tolist()], [*cut.tolist(), len(part)]):
            if i == z:
                continue
            if part[i] != now:
                now, model, rows = part[i], None, []
            if kind[i] == 0:
                rows.append(b.slice(i, z - i))
                continue
            if model is None:
                model, rows = _Shard(rows or [b.slice(0, 0)]), []
            out = []
            for data in b.column(9).slice(i, z - i):
                counts, hi, lo = unpack_grams(data.as_buffer(), ORDER + 1)
                m = np.repeat(np.arange(ORDER, -1, -1), counts)
                got, at, (a, sole) = model.find(0, m, hi, lo)
                share, alone = np.where(got, a[at], 0.0).astype("<f4"), got & sole[at].astype(bool)
                short = m < ORDER
                got, at, (g,) = model.find(1, m[short], hi[short], lo[short])
                out.append(_squeeze(_planes(share) + _planes(np.where(got, g[at], 1.0).astype("<f4")) + np.packbits(alone).tobytes()))
            yield pa.RecordBatch.from_arrays([b.column(8).slice(i, z - i), pa.array(np.full(z - i, now), pa.int32()), pa.array(out, pa.binary())], names=["block", "part", "data"])


def in_blocks(batches: Iterator[pa.RecordBatch], text: int) -> Iterator[tuple[int, bytes]]:
    """(block, payload) of neighbouring rows of at most BLOCK bytes of text, or one row. A block's name follows from
    what it holds, so a task that is run again and deals its rows otherwise cannot pass for the first."""
    held, size = [], 0

    def done() -> tuple[int, bytes]:
        sink = pa.BufferOutputStream()
        with pa.ipc.new_stream(sink, held[0].schema, options=pa.ipc.IpcWriteOptions(compression=CODEC)) as w:
            for b in held:
                w.write_batch(b)
        payload = sink.getvalue().to_pybytes()
        return int.from_bytes(hashlib.blake2b(payload, digest_size=8).digest(), "little", signed=True), payload

    for b in slices(batches, text, SLICE):
        n = pc.sum(pc.binary_length(b.column(text))).as_py() or 0
        if held and size + n > BLOCK:
            yield done()
            held, size = [], 0
        held.append(b)
        size += n
    if held:
        yield done()


def _read(payload) -> list[pa.RecordBatch]:
    return list(pa.ipc.open_stream(payload))


def _questions(texts: list[pa.Array], parts: int):
    """(levels, order, part, places): the n-grams of a block by length, the order in which they are asked, the part of each
    in that order, and for each window of each text slice the places of its n-grams among the longest."""
    found = [[(hi, lo) for hi, lo, _, _ in windows(t)] for t in texts]
    flat = [x for f in found for x in f] or [(np.zeros(0, np.int64),) * 2]
    hi, lo, inverse = distinct(np.concatenate([x[0] for x in flat]), np.concatenate([x[1] for x in flat]))
    places, at = [], 0
    for f in found:
        places.append([])
        for h, _ in f:
            places[-1].append(inverse[at : at + len(h)])
            at += len(h)
    levels = chain(hi, lo)
    m = np.repeat(np.arange(ORDER, -1, -1), [len(x[0]) for x in levels])
    every = np.concatenate([x[0] for x in levels]), np.concatenate([x[1] for x in levels])
    part = shard(*every, m, parts)
    order = np.argsort(part, kind="stable")
    return levels, every, m, order, part[order], places


def log_probabilities(levels: list, share: list[np.ndarray], left: list[np.ndarray], alone: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """(log p, log p as if n-grams that one text alone holds were unseen) of the longest n-grams, from what is known of
    each level, longest first."""
    p = q = np.full(len(levels[-1][0]), 1.0 / POINTS)
    for k in range(ORDER - 1, -1, -1):
        _, _, suf, ctx = levels[k]
        g = left[k + 1][ctx]
        p, q = share[k] + g * p[suf], np.where(alone[k], 0.0, share[k]) + g * q[suf]
    with np.errstate(divide="ignore"):
        return np.log(p), np.log(q)


def score(docs: DataFrame, model: DataFrame, extra: Callable[[pa.Array, pa.RecordBatch], pa.Array] | None = None, extra_type: str = "double", text_col: str = "text", sure_col: str = "sure") -> DataFrame:
    """docs without their text, with perplexity (3 decimals; null for null or empty texts), n_symbols, and extra(texts,
    rows). Rows with `sure` are scored as if the n-grams that they alone hold were unseen. docs are read twice and must give
    their rows in the same order both times (see common.steady); otherwise the job fails."""
    spark = docs.sparkSession
    parts = max(int(spark.conf.get("spark.sql.shuffle.partitions")), -(-model.count() // SHARD_ROWS))
    at, sure = docs.columns.index(text_col), docs.columns.index(sure_col)

    def ask(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for block, payload in in_blocks(batches, at):
            levels, (hi, lo), m, order, part, _ = _questions([b.column(at) for b in _read(payload)], parts)
            edge = np.searchsorted(part, np.arange(parts + 1))
            own = np.flatnonzero(np.diff(edge))
            data = []
            for p in own.tolist():
                o = order[edge[p] : edge[p + 1]]
                data.append(pack_grams(np.bincount(ORDER - m[o], minlength=ORDER + 1), hi[o], lo[o]))
            yield pa.RecordBatch.from_arrays([pa.array(own, pa.int32()), pa.array([block] * len(own), pa.int64()), pa.array(data, pa.binary())], names=["part", "block", "data"])

    def payloads(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for block, payload in in_blocks(batches, at):
            yield pa.RecordBatch.from_arrays([pa.array([block], pa.int64()), pa.array([parts], pa.int32()), pa.array([payload], pa.binary())], names=["block", "part", "data"])

    rest = [i for i in range(len(docs.columns)) if i != at]
    names = [docs.columns[i] for i in rest]

    def meet(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, answers = None, {}
        for b in batches:
            for block, part, data in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2)):
                if block != now:
                    now, answers = block, {}
                if part < parts:
                    answers[part] = data.as_buffer()
                    continue
                yield from _scored(_read(data.as_buffer()), answers)

    def _scored(rows: list[pa.RecordBatch], answers: dict) -> Iterator[pa.RecordBatch]:
        levels, _, m, order, part, places = _questions([b.column(at) for b in rows], parts)
        share, left, alone = np.zeros(len(m)), np.ones(len(m)), np.zeros(len(m), bool)
        edge = np.searchsorted(part, np.arange(parts + 1))
        for p in np.flatnonzero(np.diff(edge)).tolist():
            o = order[edge[p] : edge[p + 1]]
            if p not in answers:
                raise RuntimeError("a block's texts were dealt otherwise when its questions were asked: the input gives its rows in no stable order")
            raw = _unsqueeze(answers[p])
            n, short = len(o), m[o] < ORDER
            share[o] = _unplanes(raw, "<f4", n)
            left[o[short]] = _unplanes(raw[4 * n :], "<f4", int(short.sum()))
            alone[o] = np.unpackbits(raw[4 * (n + int(short.sum())) :], count=n).astype(bool)
        cut = np.cumsum([len(x[0]) for x in levels])[:-1]
        p, q = log_probabilities(levels, *(np.split(x, cut) for x in (share, left, alone)))
        for b, place in zip(rows, places):
            n = pc.fill_null(pc.utf8_length(b.column(at)), 0).to_numpy(zero_copy_only=False).astype(np.int64)
            own = b.column(sure).to_numpy(zero_copy_only=False).astype(bool)
            total = np.zeros(len(n))
            for (_, _, where, text), to in zip(windows(b.column(at)), place):
                total += np.where(own, np.bincount(text, q[to][where], len(n)), np.bincount(text, p[to][where], len(n)))
            with np.errstate(invalid="ignore", divide="ignore"):
                ppl = np.round(np.exp(-total / n), 3)
            more = [extra(b.column(at), b)] if extra else []
            yield pa.RecordBatch.from_arrays([*(b.column(i) for i in rest), pa.array(ppl, mask=n == 0), pa.array(n), *more], names=[*names, "perplexity", "n_symbols", *(["extra"] if extra else [])])

    asked = docs.mapInArrow(ask, "part int, block long, data binary")
    none = lambda kind: F.lit(None).cast(kind)
    known = model.select(shard_sql(parts).alias("part"), F.lit(0).alias("kind"), "m", "hi", "lo", "a", "g", "sole", none("long").alias("block"), none("binary").alias("data"))
    asked = asked.select("part", F.lit(1).alias("kind"), none("int").alias("m"), *(none("long").alias(k) for k in ("hi", "lo")), *(none("double").alias(k) for k in ("a", "g")), none("boolean").alias("sole"), "block", "data")
    answers = known.unionByName(asked).repartition(parts, "part").sortWithinPartitions("part", "kind").mapInArrow(_answer, "block long, part int, data binary")
    both = answers.unionByName(docs.mapInArrow(payloads, "block long, part int, data binary")).repartition(4 * parts, "block").sortWithinPartitions("block", "part")
    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema if f.name != text_col)
    return both.mapInArrow(meet, f"{fields}, perplexity double, n_symbols long" + (f", extra {extra_type}" if extra else ""))
