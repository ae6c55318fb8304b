"""Collection Burrows-Wheeler transform and common prefixes, one symbol per string and round.

Strings are aligned at their ends. Round j puts the j-th last symbol of every
string that has one before the suffix inserted in the round before, which gives
the place of the new suffix in the order of all suffixes: the symbols of the
transform, sorted stably, are the first symbols of the suffixes. The common
prefix of a new suffix with its neighbour of the same first symbol is one more
than the least common prefix between the places of the two symbols in the old
order. The state (transform, common prefixes, owners) of a collection beyond a
bound lies in sequential files that each round reads from front to back and
writes anew.
"""

from __future__ import annotations

import uuid

import numpy as np
from pyarrow import fs

BLOCK = 1 << 20  # entries written at once
KINDS = {"bwt": np.uint16, "lcp": np.uint8, "owner": np.int32, "offset": np.int32}


class _Memory:
    """The columns of the state of a small collection."""

    def __init__(self):
        self.columns: dict[str, np.ndarray] = {}

    def write(self, **columns: np.ndarray) -> None:
        self.columns |= {k: x.astype(KINDS[k], copy=False) for k, x in columns.items()}

    def read(self, k: str) -> np.ndarray:
        return self.columns[k]

    def drop(self) -> None:
        self.columns.clear()


class _Files:
    """The columns of the state, each in a sequential file of its own in the folder that all executors share; a round
    writes new files and drops those of the round before. Whatever ends the construction, the files go."""

    def __init__(self, folder: str):
        self.system, base = fs.FileSystem.from_uri(folder)
        self.base = f"{base}/columnwise-{uuid.uuid4().hex}"
        self.system.create_dir(self.base, recursive=True)
        self.names: dict[str, str] = {}

    def write(self, **columns: np.ndarray) -> None:
        for k, x in columns.items():
            new, old = f"{self.base}/{k}-{uuid.uuid4().hex}", self.names.get(k)
            with self.system.open_output_stream(new) as out:
                for i in range(0, len(x), BLOCK):
                    out.write(np.ascontiguousarray(x[i : i + BLOCK].astype(KINDS[k], copy=False)))
            self.names[k] = new
            if old:
                self.system.delete_file(old)

    def read(self, k: str) -> np.ndarray:
        with self.system.open_input_stream(self.names[k]) as f:
            return np.frombuffer(f.read(), KINDS[k])

    def drop(self) -> None:
        self.system.delete_dir(self.base)


class _Least:
    """Least value of any range, from minima over powers of two."""

    def __init__(self, x: np.ndarray):
        self.levels = [x]
        step = 1
        while 2 * step <= len(x):
            below = self.levels[-1]
            self.levels.append(np.minimum(below[:-step], below[step:]))
            step *= 2

    def __call__(self, a: np.ndarray, z: np.ndarray) -> np.ndarray:
        """Over [a, z), which must not be empty."""
        out = np.empty(len(a), self.levels[0].dtype)
        level = np.frexp((z - a).astype(np.float64))[1] - 1
        for k in np.unique(level).tolist():
            own = level == k
            t = self.levels[k]
            out[own] = np.minimum(t[a[own]], t[z[own] - (1 << k)])
        return out


def suffix_order(data: np.ndarray, ends: np.ndarray, cap: int = 255, in_memory: int = 64 << 20, folder: str | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(bwt, lcp, owner, offset) in the order of all suffixes of the strings, the empty ones first.

    data: symbols 0 to 255 of all strings, one after another; ends: where each string ends. bwt: symbol + 1, or 0
    before a whole string. lcp: common prefix with the suffix before, at most `cap` (255 or less). Equal suffixes
    lie by the order of their strings' earlier symbols, empty ones by string. A state of more than `in_memory` bytes
    lies in files in `folder` (the URI of one that all executors share), of which a round holds one or two columns at a time, and the minima of the common prefixes.
    """
    m = len(ends)
    begin = np.concatenate([[0], ends[:-1]])
    size = ends - begin
    small = (len(data) + m) * sum(np.dtype(k).itemsize for k in KINDS.values()) <= in_memory or folder is None
    files = _Memory() if small else _Files(folder)
    try:
        files.write(bwt=np.zeros(m), lcp=np.zeros(m), owner=np.arange(m), offset=size)
        place = np.arange(m)  # of each string's last inserted suffix
        for j in range(1, int(size.max(initial=0)) + 1):
            live = np.flatnonzero(size >= j)
            bwt, lcp = files.read("bwt").copy(), files.read("lcp")
            at = place[live]
            bwt[at] = data[ends[live] - j].astype(np.uint16) + 1
            order = np.argsort(bwt, kind="stable")  # of small integers, this is a counting sort
            order = order[np.searchsorted(bwt[order], 1) :]
            rank = np.empty(len(bwt), np.int64)
            rank[order] = np.arange(len(order))
            own = rank[at]
            least = _Least(lcp)
            symbol = bwt[order]

            def shared(r: np.ndarray) -> np.ndarray:
                """Common prefix of the suffixes of ranks r - 1 and r, by their first symbols' places."""
                out = np.zeros(len(r), np.uint8)
                same = np.flatnonzero((r > 0) & (symbol[r] == symbol[r - 1]))
                if len(same):
                    out[same] = np.minimum(least(order[r[same] - 1] + 1, order[r[same]] + 1).astype(np.int64) + 1, cap)
                return out

            new = np.zeros(len(bwt) + len(live), bool)
            new[m + own] = True
            old = ~new
            next_bwt, next_lcp = np.zeros(len(new), np.uint16), np.zeros(len(new), np.uint8)
            next_bwt[old], next_lcp[old] = bwt, lcp
            next_lcp[m + own] = shared(own)
            after = own[own + 1 < len(order)] + 1
            next_lcp[m + after] = shared(after)
            moved: dict[str, np.ndarray] = {}
            for k, x in (("owner", live), ("offset", size[live] - j)):
                col = np.empty(len(new), np.int32)
                col[old] = files.read(k)
                col[m + own] = x
                moved[k] = col
            files.write(bwt=next_bwt, lcp=next_lcp, **moved)
            place[live] = m + own
        return files.read("bwt"), files.read("lcp"), files.read("owner"), files.read("offset")
    finally:
        files.drop()


def repeats(data: np.ndarray, ends: np.ndarray, doc: np.ndarray, length: int, folder: str | None = None) -> tuple[np.ndarray, np.ndarray]:
    """(string, offset) of every place where a substring of `length` symbols starts that also starts in a string of a
    lesser `doc`."""
    _, lcp, owner, offset = suffix_order(data, ends, cap=length, folder=folder)
    if not len(owner):
        return owner, offset
    first = np.flatnonzero(np.concatenate([[True], lcp[1:] < length]))
    least = np.minimum.reduceat(doc[owner], first)
    hit = doc[owner] > np.repeat(least, np.diff(np.append(first, len(owner))))
    return owner[hit], offset[hit]
