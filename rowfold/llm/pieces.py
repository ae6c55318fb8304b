"""SentencePiece encoding and decoding by a batched Viterbi search in numpy.

Texts become words (a run of word-start marks and what follows up to the next
space; no piece goes on from a word into the blanks behind it);
the distinct words of a batch are grouped by length, and all words of one length
advance together: for each end position and piece length, the substring hashes
of the whole group probe the sorted hashes of the pieces, and
vectorised maxima keep the best score and a back-pointer. Characters that no
piece covers fall back to byte pieces. The objective is the sum of the piece
scores in the model file, as of a unigram model; ties go to the longer last
piece.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame

from rowfold.llm.common import slices, utf8

MARK = "▁"
BASE = np.uint64(0x9E3779B97F4A7C15)
WORD_END = re.compile("(?<=[^ ]) ")  # the first blank of a run; the others belong to the word after it
LONG = 64  # words longer than this are searched one by one
FOREIGN = np.uint64(0x110000)  # stands for a mark that the text itself holds


@dataclass(frozen=True)
class Pieces:
    """Lookup tables of a model, small enough to ship: a few hundred kilobytes for 32,000 pieces."""

    keys: np.ndarray  # sorted hashes, times SPREAD
    first: np.ndarray  # by the high bits of a hash, the first key that could be it; a last entry ends the keys
    run: int  # most keys with the same high bits
    ids: np.ndarray
    scores: np.ndarray
    longest: int
    byte_ids: np.ndarray  # of bytes 0 to 255
    unknown: float
    utf8: tuple[bytes, ...]  # bytes of each id, the mark as a space; control pieces are empty


def load_pieces(model_file: str) -> Pieces:
    """Read a piece model on the driver."""
    import sentencepiece

    sp = sentencepiece.SentencePieceProcessor(model_file=model_file)
    n = sp.get_piece_size()
    byte_ids, rows, texts = np.full(256, -1, np.int32), [], []
    for i in range(n):
        p = sp.id_to_piece(i)
        if sp.is_byte(i):
            byte_ids[int(p[3:5], 16)] = i
            texts.append(bytes([int(p[3:5], 16)]))
        elif sp.is_control(i) or sp.is_unknown(i) or sp.is_unused(i):
            texts.append(b"")
        else:
            texts.append(p.replace(MARK, " ").encode())
            if p.strip(MARK) and MARK in p[1:]:
                raise ValueError("a piece goes on over a word's end")
            rows.append((p, i, sp.get_score(i)))
    if (byte_ids < 0).any():
        raise ValueError("the model has no byte pieces to fall back to")
    keys = np.array([hash_of(p) for p, _, _ in rows], np.uint64) * SPREAD
    order = np.argsort(keys)
    if (np.diff(keys[order]) == 0).any():
        raise ValueError("two pieces share a hash")
    scores = np.array([s for _, _, s in rows], np.float64)
    first, run = _directory(keys[order])
    return Pieces(keys[order], first, run, np.array([i for _, i, _ in rows], np.int32)[order], scores[order], max(len(p) for p, _, _ in rows), byte_ids, float(scores.min()) - 10.0, tuple(texts))


HIGH = 18  # bits of a hash that lead to its place among the sorted keys
SPREAD = np.uint64(0xBF58476D1CE4E5B9)  # odd, so no two hashes meet; hashes of short pieces are small numbers without it


def _directory(keys: np.ndarray) -> tuple[np.ndarray, int]:
    """Where the sorted keys of each value of the high bits begin, and the most keys of one value."""
    high = (keys >> np.uint64(64 - HIGH)).astype(np.int64)
    first = np.searchsorted(high, np.arange((1 << HIGH) + 1)).astype(np.int32)
    return first, int(np.diff(first).max(initial=0))


def probe(p: Pieces, key: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(place among the sorted keys, whether the key is there). The high bits of a hash lead to the few sorted keys that
    share them, which are compared one after another."""
    key = key * SPREAD
    high = (key >> np.uint64(64 - HIGH)).astype(np.int32)
    at = p.first[high]
    found = p.keys.take(at, mode="clip") == key
    if p.run > 1:
        more = np.flatnonzero(~found & (p.first[high + 1] - at > 1))
        for i in range(1, p.run):
            if not len(more):
                break
            hit = p.keys.take(at[more] + i, mode="clip") == key[more]
            at[more[hit]] += i
            found[more[hit]] = True
            more = more[~hit]
    return np.where(found, at, 0), found


def hash_of(s: str) -> np.uint64:
    with np.errstate(over="ignore"):
        h = np.uint64(0)
        for c in s:
            h = h * BASE + np.uint64(ord(c) + 1)
    return h


def viterbi(words: np.ndarray, p: Pieces) -> tuple[np.ndarray, np.ndarray]:
    """words: (n, L) code points of equal-length words. Returns back (n, L+1), the length of the best last piece
    ending there, and piece (n, L+1), its id or -1 for a character without piece."""
    n, length = words.shape
    power = BASE ** np.arange(length + 1, dtype=np.uint64)
    prefix = np.zeros((n, length + 1), np.uint64)
    for j in range(length):
        prefix[:, j + 1] = prefix[:, j] * BASE + words[:, j] + np.uint64(1)
    best = np.full((n, length + 1), -np.inf)
    best[:, 0] = 0
    back, piece = np.zeros((n, length + 1), np.int32), np.full((n, length + 1), -1, np.int32)
    for j in range(1, length + 1):
        for k in range(min(p.longest, j), 0, -1):
            key = prefix[:, j] - prefix[:, j - k] * power[k]
            at, hit = probe(p, key)
            if k == 1:
                score = best[:, j - 1] + np.where(hit, p.scores[at], p.unknown)
                ident = np.where(hit, p.ids[at], -1)
            else:
                score = np.where(hit, best[:, j - k] + p.scores[at], -np.inf)
                ident = p.ids[at]
            better = score > best[:, j]
            best[:, j] = np.where(better, score, best[:, j])
            back[:, j] = np.where(better, k, back[:, j])
            piece[:, j] = np.where(better, ident, piece[:, j])
    return back, piece


def viterbi_long(word: np.ndarray, p: Pieces) -> tuple[np.ndarray, np.ndarray]:
    """The same for one long word: all substrings of a length are hashed and looked up at once, then one scan."""
    length = len(word)
    found = []
    with np.errstate(over="ignore"):
        h = np.zeros(length, np.uint64)
        for k in range(1, min(p.longest, length) + 1):
            h = h[: length - k + 1] * BASE + word[k - 1 :] + np.uint64(1)
            at, hit = probe(p, h)
            where = np.flatnonzero(hit)
            found.append((where + k, np.full(len(where), k), p.ids[at[where]], p.scores[at[where]]))
    end = np.concatenate([x[0] for x in found])
    size, ident, score = (np.concatenate([x[i] for x in found]) for i in (1, 2, 3))
    order = np.lexsort((-size, end))
    end, size, ident, score = end[order], size[order].tolist(), ident[order].tolist(), score[order].tolist()
    first = np.searchsorted(end, np.arange(length + 2)).tolist()
    best, back, piece = [0.0] * (length + 1), [0] * (length + 1), [-1] * (length + 1)
    for j in range(1, length + 1):
        top, b, q = -np.inf, 1, -1
        for i in range(first[j], first[j + 1]):
            v = best[j - size[i]] + score[i]
            if v > top:
                top, b, q = v, size[i], ident[i]
        if not (first[j] < first[j + 1] and size[first[j + 1] - 1] == 1):
            v = best[j - 1] + p.unknown
            if v > top:
                top, b, q = v, 1, -1
        best[j], back[j], piece[j] = top, b, q
    return np.array(back, np.int32), np.array(piece, np.int32)


def _trace(words: np.ndarray, back: np.ndarray, piece: np.ndarray, p: Pieces) -> tuple[np.ndarray, np.ndarray]:
    """Follow the back-pointers of all words of a group at once: (ids row after row, count for each row)."""
    n, length = words.shape
    at, rows, places, ids = np.full(n, length), [], [], []
    live = np.arange(n)
    while len(live):
        j = at[live]
        rows.append(live)
        places.append(j)
        ids.append(piece[live, j])
        at[live] = j - back[live, j]
        live = live[at[live] > 0]
    rows, places, ids = np.concatenate(rows), np.concatenate(places), np.concatenate(ids)
    order = np.lexsort((places, rows))
    rows, places, ids = rows[order], places[order], ids[order]
    lost = np.flatnonzero(ids < 0)
    if len(lost):  # bytes of the characters that no piece covers
        spelled = [(MARK if c == FOREIGN else chr(c)).encode() for c in words[rows[lost], places[lost] - 1].tolist()]
        times = np.ones(len(ids), np.int64)
        times[lost] = [len(x) for x in spelled]
        out = np.repeat(ids, times)
        out[out < 0] = p.byte_ids[np.frombuffer(b"".join(spelled), np.uint8)]
        rows, ids = np.repeat(rows, times), out
    return ids, np.bincount(rows, minlength=n)


def encode_words(words: list[str], p: Pieces) -> tuple[np.ndarray, np.ndarray]:
    """Ids of all words, one after another, and each word's number of ids. Words come without their first mark; further
    blanks before them are marks too."""
    size = np.array([len(w) + 1 for w in words], np.int64)
    counts, parts = np.zeros(len(words), np.int64), {}
    for length in np.unique(size).tolist():
        which = np.flatnonzero(size == length)
        text = "".join(MARK + words[i] for i in which)
        codes = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64).reshape(len(which), length)
        codes = np.where((codes == ord(MARK)) & (np.arange(length) > 0), FOREIGN, codes)
        codes = np.where(codes == ord(" "), np.uint64(ord(MARK)), codes)
        step = max(1, 2_000_000 // length)
        for at in range(0, len(which), step):
            own = codes[at : at + step]
            if length <= LONG:
                back, piece = viterbi(own, p)
            else:
                both = [viterbi_long(w, p) for w in own]
                back, piece = np.stack([x[0] for x in both]), np.stack([x[1] for x in both])
            ids, n = _trace(own, back, piece, p)
            counts[which[at : at + step]] = n
            upto = np.concatenate([[0], np.cumsum(n)])
            for k, i in enumerate(which[at : at + step].tolist()):
                parts[i] = ids[upto[k] : upto[k + 1]]
    return (np.concatenate([parts[i] for i in range(len(words))]) if words else np.zeros(0, np.int32)), counts


def gather(starts: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """Indexes of the ranges [start, start + count), one after another."""
    upto = np.cumsum(counts)
    return np.arange(upto[-1] if len(upto) else 0) + np.repeat(starts - (upto - counts), counts)


def encode_batch(text: pa.Array, p: Pieces) -> tuple[np.ndarray, np.ndarray]:
    """Ids of all texts, one after another, and each text's number of ids. A null or empty text has none."""
    text = text.fill_null("")
    if pc.any(pc.or_(pc.match_substring(text, "  "), pc.starts_with(text, " "))).as_py():
        split = pa.array([WORD_END.split(t) for t in text.to_pylist()], pa.list_(pa.string()))
    else:
        split = pc.split_pattern(text, " ")
    words = split.flatten().dictionary_encode()
    ids, counts = encode_words(words.dictionary.to_pylist(), p)
    starts = np.cumsum(counts) - counts
    per_word = words.indices.to_numpy(zero_copy_only=False).astype(np.int64)
    empty = pc.equal(text, "").to_numpy(zero_copy_only=False)
    words_of = np.diff(np.asarray(split.offsets))
    keep = ~np.repeat(empty, words_of)
    per_word, words_of = per_word[keep], np.where(empty, 0, words_of)
    flat = ids[gather(starts[per_word], counts[per_word])] if len(per_word) else np.zeros(0, np.int32)
    upto = np.concatenate([[0], np.cumsum(counts[per_word])])
    ends = upto[np.cumsum(words_of)]
    return flat.astype(np.int32), np.diff(np.concatenate([[0], ends]))


def decode_batch(ids: np.ndarray, counts: np.ndarray, p: Pieces) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes of all texts and their offsets: pieces laid end to end; the space of each text's first mark goes."""
    size = np.array([len(x) for x in p.utf8], np.int64)
    blob = np.frombuffer(b"".join(p.utf8), np.uint8)
    start = np.cumsum(size) - size
    n = size[ids]
    flat = blob[gather(start[ids], n)] if len(ids) else np.zeros(0, np.uint8)
    bytes_upto = np.concatenate([[0], np.cumsum(n)])
    off = bytes_upto[np.concatenate([[0], np.cumsum(counts)])]
    lead = off[:-1][counts > 0]  # the dummy space before each text
    off = off - np.concatenate([[0], np.cumsum(counts > 0)])
    return np.delete(flat, lead), off


def encode(docs: DataFrame, model_file: str, id_col: str = "doc_id", text_col: str = "text", batch_bytes: int = 4 << 20) -> DataFrame:
    """One row per input row: id, ids (array of int), n_pieces, n_byte_pieces, exact (decoding gave the text back).

    A null or empty text has no ids and counts as exact. Marks within a text are spelled as bytes, so every text
    comes back. Ids may be null or repeated, the table empty; further columns are ignored. No text is cut.
    """
    p = load_pieces(model_file)
    shipped = docs.sparkSession.sparkContext.broadcast(p)  # bounded by the vocabulary

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        p = shipped.value
        is_byte = np.zeros(len(p.utf8), bool)
        is_byte[p.byte_ids] = True
        for b in slices(batches, 1, batch_bytes):
            ids, counts = encode_batch(b.column(1), p)
            upto = np.concatenate([[0], np.cumsum(counts)])
            raw, off = utf8(b.column(1))
            back, back_off = decode_batch(ids, counts, p)
            raw = raw[off[0] : off[-1]]
            same = len(raw) == len(back) and np.array_equal(off - off[0], back_off) and np.array_equal(raw, back)
            exact = np.ones(len(counts), bool) if same else np.array([np.array_equal(raw[off[i] - off[0] : off[i + 1] - off[0]], back[back_off[i] : back_off[i + 1]]) for i in range(len(counts))])
            byte_upto = np.concatenate([[0], np.cumsum(is_byte[ids])])
            yield pa.RecordBatch.from_arrays(
                [b.column(0), pa.ListArray.from_arrays(pa.array(upto.astype(np.int32)), pa.array(ids)), pa.array(counts), pa.array(byte_upto[upto[1:]] - byte_upto[upto[:-1]]), pa.array(exact)],
                names=[id_col, "ids", "n_pieces", "n_byte_pieces", "exact"],
            )

    src = docs.select(id_col, text_col)
    return src.mapInArrow(work, f"{id_col} {dict(src.dtypes)[id_col]}, ids array<int>, n_pieces long, n_byte_pieces long, exact boolean")


def decode(encoded: DataFrame, model_file: str, id_col: str = "doc_id", ids_col: str = "ids") -> DataFrame:
    """id and text of encoded rows; null ids give a null text. Bytes that are no UTF-8 become replacement marks."""
    shipped = encoded.sparkSession.sparkContext.broadcast(load_pieces(model_file))

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        p = shipped.value
        for b in batches:
            col = b.column(1)
            counts = np.array([0 if v is None else v for v in pc.list_value_length(col).to_pylist()], np.int64)
            raw, off = decode_batch(np.asarray(col.flatten(), dtype=np.int64), counts, p)
            raw = raw.tobytes()
            text = [None if null else raw[off[i] : off[i + 1]].decode("utf-8", "replace") for i, null in enumerate(col.is_null().to_pylist())]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(text, pa.string())], names=[id_col, "text"])

    src = encoded.select(id_col, ids_col)
    return src.mapInArrow(work, f"{id_col} {dict(src.dtypes)[id_col]}, text string")
