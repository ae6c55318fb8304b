"""Exact removal of byte strings that an earlier document holds, by a column-wise suffix construction.

Whole corpora do not fit one construction, so places that could repeat are found
first: the least hash of the 20-byte strings inside a 50-byte window depends on
the window alone, so equal windows meet under the same anchor. Neighbouring windows
with one anchor make a run; runs are dealt by anchor, and an anchor of a single
document can be passed over. Equal runs fall into one class, of which the least
document speaks. Where classes differ, the bytes of their runs go, grouped by
anchor, through the column-wise construction of transform and common prefixes,
whose stretches of common prefixes of 50 bytes and more name every window that
also starts in a lesser document.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rowfold.llm.columnwise import repeats
from rowfold.llm.common import parts_for, release, shared_dir, slices, staged, text_bytes, utf8
from rowfold.llm.jaccard import _groups
from rowfold.llm.shingles import PLACES, U, mix, powers

BATCH = 1 << 20
ANCHOR = 20  # bytes of the strings whose least hash is a window's anchor
AT_ONCE = 3_000  # strings of one construction


def prefix_hash(raw: np.ndarray) -> np.ndarray:
    """Sums from which the hash of any stretch follows by subtraction."""
    _, down = powers(len(raw))
    s = np.zeros(len(raw) + 1, U)
    np.cumsum((raw.astype(U) + U(1)) * down[: len(raw)], out=s[1:], dtype=U)
    return s


def runs(raw: np.ndarray, off: np.ndarray, length: int) -> tuple[np.ndarray, ...]:
    """(text, start, windows, anchor, content, left, right) of the runs of all texts.

    `windows` neighbouring windows from `start` (within its text) have their anchor at one place, the first on ties, so
    equal windows have it at equal places. content is the hash of the run's bytes. left and right are hashes (8 bits) of the
    bytes before and after the anchor's string, half as many as a window holds beside it: of two runs with a common window
    and one anchor, one of the two agrees, unless it reaches over the end of a text, which is marked by 0."""
    n = len(raw)
    if n < length:
        return tuple(np.zeros(0, t) for t in (np.int64, np.int64, np.int64, U, U, np.uint8, np.uint8))
    up, _ = powers(n)
    s = prefix_hash(raw)
    low = mix((s[ANCHOR:] - s[:-ANCHOR]) * up[: n - ANCHOR + 1])
    w = length - ANCHOR + 1
    size, reach, place = 1, low, np.arange(len(low), dtype=np.int32)

    def least(a: int, b: int, k: int) -> tuple[np.ndarray, np.ndarray]:
        first = reach[a : a + k] <= reach[b : b + k]
        return np.where(first, reach[a : a + k], reach[b : b + k]), np.where(first, place[a : a + k], place[b : b + k])

    while 2 * size <= w:
        reach, place = least(0, size, len(reach) - size)
        size *= 2
    reach, place = least(0, w - size, len(low) - w + 1)
    begins, ends = off[:-1], off[1:]
    good = np.zeros(len(reach) + 1, np.int32)  # windows that lie within one text
    fits = ends - begins >= length
    np.add.at(good, begins[fits], 1)
    np.add.at(good, ends[fits] - length + 1, -1)
    inside = np.cumsum(good[:-1]) > 0
    first = inside.copy()
    first[1:] &= (place[1:] != place[:-1]) | ~inside[:-1]
    first[begins[fits]] = True
    start = np.flatnonzero(first)
    text = np.searchsorted(off, start, side="right") - 1
    stop = np.minimum(np.append(start[1:], len(reach)), ends[text] - length + 1)
    at = place[start].astype(np.int64)

    def stretch(a: np.ndarray, z: np.ndarray) -> np.ndarray:
        return mix((s[z] - s[a]) * up[a] + (z - a).astype(U) * PLACES[4])

    half = (length - ANCHOR) // 2

    def side(a: np.ndarray, z: np.ndarray) -> np.ndarray:
        whole = (a >= begins[text]) & (z <= ends[text])
        a, z = np.where(whole, a, 0), np.where(whole, z, 0)
        return np.where(whole, (stretch(a, z) >> U(40)).astype(np.int64) % 255 + 1, 0).astype(np.uint8)

    content = stretch(start, stop + length - 1)
    return text, start - begins[text], stop - start, reach[start] >> U(16), content >> U(24), side(at - half, at + ANCHOR), side(at, at + ANCHOR + half)


def _part(key: np.ndarray, parts: int) -> np.ndarray:
    return ((mix(key) >> U(32)) * U(parts) >> U(32)).astype(np.int32)


def _planes(x: np.ndarray, width: int) -> bytes:
    """The low `width` bytes of numbers, byte by byte of all: equal high bytes lie together and compress."""
    wide = x.astype("<u8").view(np.uint8).reshape(len(x), 8)
    return np.ascontiguousarray(wide[:, :width].T).tobytes()


def _from_planes(raw: np.ndarray, at: int, n: int, width: int) -> np.ndarray:
    wide = np.zeros((n, 8), np.uint8)
    wide[:, :width] = raw[at : at + n * width].reshape(width, n).T
    return wide.view("<u8").reshape(-1)


def pack(columns: list[tuple[np.ndarray, int]], doc: np.ndarray, key: np.ndarray) -> bytes:
    """A blob of rows: a table of the texts (doc, key), then for each row the step to its text, and its columns. Rows are
    sorted by text."""
    new = np.ones(len(doc), bool)
    new[1:] = (doc[1:] != doc[:-1]) | (key[1:] != key[:-1])
    head = np.array([int(new.sum()), len(doc)], "<i8").tobytes()
    return b"".join([head, doc[new].astype("<i8").tobytes(), key[new].astype("<i4").tobytes(), new.astype(np.uint8).tobytes(), *(_planes(x, w) for x, w in columns)])


def unpack(blob: pa.Buffer, widths: tuple[int, ...]) -> tuple[np.ndarray, ...]:
    raw = np.frombuffer(blob, np.uint8)
    t, m = (int(x) for x in raw[:16].view("<i8"))
    docs, keys = raw[16 : 16 + 8 * t].copy().view("<i8"), raw[16 + 8 * t : 16 + 12 * t].copy().view("<i4")
    at = 16 + 12 * t
    which = np.cumsum(raw[at : at + m], dtype=np.int64) - 1
    at += m
    out = [docs[which], keys[which].astype(np.int64)]
    for w in widths:
        out.append(_from_planes(raw, at, m, w))
        at += m * w
    return tuple(out)


#: Kinds of rows: 0 runs by part of the anchors; 1 hits and 2 asks by part of the documents; 9 texts.
ROWS = "part int, kind int, doc long, text_key int, data binary"
RUN = (4, 1, 6, 5, 1, 1)  # start, windows, anchor, content, left, right
HIT = (4, 2)  # start, windows that repeat an earlier document
ASK = (4, 2, 6)  # start, windows, anchor of bytes wanted


def _rows(part, kind: int, data: list[bytes]) -> pa.RecordBatch:
    n = len(data)
    return pa.RecordBatch.from_arrays([pa.array(part, pa.int32()), pa.array(np.full(n, kind, np.int32)), pa.nulls(n, pa.int64()), pa.nulls(n, pa.int32()), pa.array(data, pa.binary())], names=["part", "kind", "doc", "text_key", "data"])


def _blobs(part: np.ndarray, doc: np.ndarray, key: np.ndarray, columns: list[tuple[np.ndarray, int]]) -> tuple[list[int], list[bytes]]:
    """One blob for each part."""
    order = np.lexsort((columns[0][0], key, doc, part))
    part = part[order]
    cut = np.flatnonzero(part[1:] != part[:-1]) + 1
    out = []
    edges = [0, *cut.tolist(), len(part)] if len(part) else []
    for a, z in zip(edges, edges[1:]):
        own = order[a:z]
        out.append(pack([(x[own], w) for x, w in columns], doc[own], key[own]))
    return [int(part[a]) for a in edges[:-1]], out


def _find_runs(src: DataFrame, length: int, parts: int) -> DataFrame:
    """Kinds 0 and 1. Of equal runs in a batch only those of the least document go out; the others are hits at once."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches, 2, BATCH):
            docs, keys = np.asarray(b.column(0)), np.asarray(b.column(1)).astype(np.int64)
            raw, off = utf8(b.column(2))
            text, *cols = runs(raw[off[0] : off[-1]], off - off[0], length)
            doc = docs[text]
            order = np.lexsort((doc, cols[3], cols[2]))
            text, doc, cols = text[order], doc[order], [x[order] for x in cols]
            new = np.ones(len(doc), bool)
            new[1:] = (cols[2][1:] != cols[2][:-1]) | (cols[3][1:] != cols[3][:-1])
            lead = np.maximum.accumulate(np.where(new, np.arange(len(doc)), 0))
            dup = doc > doc[lead]
            if dup.any():
                d, k = doc[dup], keys[text[dup]]
                yield _rows(*(lambda x: (x[0], 1, x[1]))(_blobs(_part(d.view(U), parts), d, k, [(cols[0][dup], 4), (cols[1][dup], 2)])))
            text, doc, cols = text[~dup], doc[~dup], [x[~dup] for x in cols]
            part, data = _blobs(_part(cols[2], parts), doc, keys[text], list(zip(cols, RUN)))
            yield _rows(part, 0, data)

    return src.mapInArrow(work, ROWS)


def agree(group: np.ndarray, value: np.ndarray, doc: np.ndarray) -> np.ndarray:
    """Rows whose value is 0, or also stands in a row of the same group and another document."""
    order = np.lexsort((doc, value, group))
    g, v, d = group[order], value[order], doc[order]
    same = (g[1:] == g[:-1]) & (v[1:] == v[:-1])
    start = np.flatnonzero(np.concatenate([[True], ~same]))
    size = np.diff(np.append(start, len(g)))
    mixed = np.repeat(d[start] != d[start + size - 1], size)
    out = np.empty(len(g), bool)
    out[order] = mixed | (v == 0)
    return out


def _compare_runs(found: DataFrame, parts: int) -> DataFrame:
    """Kinds 1 and 2: of runs that share an anchor, hits by equal content, and those whose bytes must be compared."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _, held in _groups(batches):
            blobs = []
            for b in held:
                kind = np.asarray(b.column(1))
                blobs += [unpack(x.as_buffer(), RUN) for x in b.column(4).filter(pa.array(kind == 0))]
                if (kind == 1).any():
                    yield b.filter(pa.array(kind == 1))
            if not blobs:
                continue
            doc, key, start, n, anchor, content, left, right = (np.concatenate(x) for x in zip(*blobs))
            blobs.clear()
            order = np.argsort(anchor, kind="stable")
            a = anchor[order]
            same = np.zeros(len(a), bool)
            same[1:] = a[1:] == a[:-1]
            same[:-1] |= same[1:]  # anchors met once are passed over
            order = order[same]
            if not len(order):
                continue
            order = order[np.lexsort((doc[order], content[order], anchor[order]))]
            doc, key, start, n, anchor, content, left, right = (x[order] for x in (doc, key, start, n, anchor, content, left, right))
            group = np.ones(len(doc), bool)
            group[1:] = anchor[1:] != anchor[:-1]
            new = group.copy()
            new[1:] |= content[1:] != content[:-1]
            lead = np.maximum.accumulate(np.where(new, np.arange(len(doc)), 0))
            hit = doc > doc[lead]
            if hit.any():
                part, data = _blobs(_part(doc[hit].view(U), parts), doc[hit], key[hit], [(start[hit], 4), (n[hit], 2)])
                yield _rows(part, 1, data)
            rest = np.flatnonzero(~hit)  # each class by its least document
            g = np.cumsum(group)[rest]
            ask = rest[agree(g, left[rest], doc[rest]) | agree(g, right[rest], doc[rest])]
            g = anchor[ask]
            at = np.flatnonzero(np.concatenate([[True], g[1:] != g[:-1]])) if len(g) else np.zeros(0, np.int64)
            if len(ask):
                size = np.diff(np.append(at, len(ask)))
                least, most = np.minimum.reduceat(doc[ask], at), np.maximum.reduceat(doc[ask], at)
                ask = ask[np.repeat(least < most, size)]
            if len(ask):
                part, data = _blobs(_part(doc[ask].view(U), parts), doc[ask], key[ask], [(start[ask], 4), (n[ask], 2), (anchor[ask], 6)])
                yield _rows(part, 2, data)

    return found.mapInArrow(work, ROWS)


def _texts(src: DataFrame, parts: int) -> DataFrame:
    """The texts as rows of kind 9, dealt like the hits."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            doc = np.asarray(b.column(0))
            yield pa.RecordBatch.from_arrays([pa.array(_part(doc.view(U), parts)), pa.array(np.full(len(doc), 9, np.int32)), b.column(0), b.column(1), b.column(2).cast(pa.binary())], names=["part", "kind", "doc", "text_key", "data"])

    return src.mapInArrow(work, ROWS)


class _Spans:
    """Hits or asks of one part, found by text."""

    def __init__(self, blobs: list, widths: tuple[int, ...]):
        cols = [np.concatenate(x) for x in zip(*(unpack(x, widths) for x in blobs))] if blobs else [np.zeros(0, np.int64)] * (2 + len(widths))
        order = np.lexsort((cols[2], cols[1], cols[0]))
        self.doc, self.key, *self.cols = (x[order] for x in cols)

    def of(self, doc: int, key: int) -> list[np.ndarray] | None:
        a, z = np.searchsorted(self.doc, doc), np.searchsorted(self.doc, doc, side="right")
        if a == z:
            return None
        b, y = a + np.searchsorted(self.key[a:z], key), a + np.searchsorted(self.key[a:z], key, side="right")
        return [c[b:y].astype(np.int64) for c in self.cols] if b < y else None


def cut_out(data: bytes, hits: list[np.ndarray] | None, length: int) -> tuple[int, int, str]:
    """(bytes removed, maximal removed runs, SHA-256 of what is left)."""
    if hits is None:
        return 0, 0, hashlib.sha256(data).hexdigest()
    start, n = hits[:2]
    edge = np.zeros(len(data) + 1, np.int32)
    np.add.at(edge, start, 1)
    np.add.at(edge, start + n + length - 1, -1)
    gone = np.cumsum(edge[:-1]) > 0
    kept = np.frombuffer(data, np.uint8)[~gone]
    return int(gone.sum()), int(np.count_nonzero(np.diff(gone.astype(np.int8), prepend=0) == 1)), hashlib.sha256(kept.tobytes()).hexdigest()


def _with_spans(batches: Iterator[pa.RecordBatch], kinds: dict[int, tuple[int, ...]]) -> Iterator[tuple[int, int, bytes, dict[int, list[np.ndarray] | None]]]:
    """(doc, key, text, spans by kind) from rows sorted by part and kind, so a part's spans are known before its texts."""
    part, found, blobs = None, None, {k: [] for k in kinds}
    for b in batches:
        for i, (p, kind) in enumerate(zip(b.column(0).to_pylist(), b.column(1).to_pylist())):
            if p != part:
                part, found, blobs = p, None, {k: [] for k in kinds}
            if kind != 9:
                blobs[kind].append(b.column(4)[i].as_buffer())
                continue
            if found is None:
                found, blobs = {k: _Spans(blobs[k], w) for k, w in kinds.items()}, {k: [] for k in kinds}
            doc, key = b.column(2)[i].as_py(), b.column(3)[i].as_py()
            yield doc, key, b.column(4)[i], {k: s.of(doc, key) for k, s in found.items()}


def _segments(rows: DataFrame, length: int, parts: int) -> DataFrame:
    """(part, data) by part of the anchors: the bytes of the runs asked for."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        wanted: list[tuple] = []  # (anchor, doc, key, start, bytes)

        def flush() -> pa.RecordBatch:
            part = _part(np.array([x[0] for x in wanted], U), parts)
            at, out = np.unique(part), []
            for p in at.tolist():
                own = np.flatnonzero(part == p).tolist()
                meta = [np.array([wanted[i][c] for i in own], "<i8").tobytes() for c in range(4)]
                size = np.array([len(wanted[i][4]) for i in own], "<i4")
                out.append(b"".join([np.array([len(own)], "<i8").tobytes(), *meta, size.tobytes(), *(wanted[i][4] for i in own)]))
            wanted.clear()
            return pa.RecordBatch.from_arrays([pa.array(at, pa.int32()), pa.array(out, pa.binary())], names=["part", "data"])

        for doc, key, text, spans in _with_spans(batches, {2: ASK}):
            if spans[2] is not None:
                data = text.as_py()
                wanted += [(a, doc, key, s, data[s : s + n + length - 1]) for s, n, a in zip(*(c.tolist() for c in spans[2]))]
                if len(wanted) > 100_000:
                    yield flush()
        if wanted:
            yield flush()

    return rows.mapInArrow(work, "part int, data binary")


def _answer(rows: DataFrame, length: int) -> DataFrame:
    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out: list[tuple] = []

        def flush() -> pa.RecordBatch:
            batch = pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out), (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.string()))], names=["doc", "n_bytes", "n_removed", "n_spans", "kept_sha256"])
            out.clear()
            return batch

        for doc, _, text, spans in _with_spans(batches, {1: HIT}):
            data = text.as_py()
            out.append((doc, len(data), *cut_out(data, spans[1], length)))
            if len(out) == 5000:
                yield flush()
        if out:
            yield flush()

    return rows.mapInArrow(work, "doc long, n_bytes long, n_removed long, n_spans long, kept_sha256 string")


def _construct(segments: DataFrame, length: int, parts: int, folder: str) -> DataFrame:
    """Hits by part of the documents, from the bytes of the runs of each part: anchors in order, whole anchors at a time."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _, held in _groups(batches):
            meta, sizes, bodies = [], [], []
            for b in held:
                for x in b.column(1):
                    raw = np.frombuffer(x.as_buffer(), np.uint8)
                    m = int(raw[:8].view("<i8")[0])
                    meta.append(raw[8 : 8 + 32 * m].copy().view("<i8").reshape(4, m))
                    sizes.append(raw[8 + 32 * m : 8 + 36 * m].copy().view("<i4"))
                    bodies.append(raw[8 + 36 * m :])
            anchor, doc, key, start = np.concatenate(meta, axis=1)
            size, body = np.concatenate(sizes).astype(np.int64), np.concatenate(bodies)
            begin = np.cumsum(size) - size
            order = np.lexsort((start, doc, anchor))
            whole = np.append(np.flatnonzero(np.diff(anchor[order])) + 1, len(order))
            a = 0
            while a < len(order):
                z = int(whole[min(np.searchsorted(whole, a + AT_ONCE), len(whole) - 1)])
                own = order[a:z]
                a = z
                n = size[own]
                at = np.arange(n.sum()) + np.repeat(begin[own] - (np.cumsum(n) - n), n)
                who, place = repeats(body[at], np.cumsum(n), doc[own], length, folder)
                if len(who):
                    d = doc[own[who]]
                    part, data = _blobs(_part(d.view(U), parts), d, key[own[who]], [(start[own[who]] + place, 4), (np.ones(len(who), np.int64), 2)])
                    yield _rows(part, 1, data)

    return segments.select("part", "data").mapInArrow(work, ROWS)


def remove_repeats(docs: DataFrame, length: int = 50, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per input row: id, n_bytes, n_removed, n_spans, kept_sha256.

    A byte goes if a string of `length` bytes that covers it also starts in a document with a lesser id, all judged
    on the input. A null text is empty (nothing to remove). Rows that repeat an id do not count as each other's
    earlier documents; a null id comes before all. An empty table gives no rows; further columns are ignored. Texts
    are taken whole, however long.
    """
    if length < ANCHOR + 1:
        raise ValueError(f"length must exceed {ANCHOR}")
    parts = parts_for(docs, text_bytes(docs, text_col), 8 << 20)
    lowest = F.lit(-(1 << 63))
    src = docs.select(F.coalesce(F.col(id_col).cast("long"), lowest).alias("doc"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    src = src.select("doc", F.expr("cast(pmod(xxhash64(text), 2147483647) as int)").alias("text_key"), "text")
    long = src.filter(F.octet_length("text") >= length)
    dealt = lambda rows: rows.repartition(parts, "part").sortWithinPartitions("part", "kind")
    spans = staged(_compare_runs(dealt(_find_runs(long, length, parts)), parts), "repeats-spans")
    release(docs.sparkSession)
    asked = _segments(dealt(spans.filter("kind = 2").unionByName(_texts(long, parts))), length, parts)
    more = staged(_construct(asked.repartition(parts, "part").sortWithinPartitions("part"), length, parts, shared_dir(docs.sparkSession)), "repeats-hits")
    del asked
    release(docs.sparkSession)
    out = _answer(dealt(spans.filter("kind = 1").unionByName(more).unionByName(_texts(src, parts))), length)
    return out.select(F.when(F.col("doc") != lowest, F.col("doc")).alias(id_col), "n_bytes", "n_removed", "n_spans", "kept_sha256")
