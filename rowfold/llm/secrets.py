"""Secret scan: fixed patterns, and a battery of randomness tests under false-discovery control.

Beside the three base patterns, every long unbroken token is a candidate. Where no
single encoding holds all of it, its longest parts that one encoding holds are
candidates instead: it is cut at '=' with something behind it, and where '/' or '+'
meets '-' or '_'. The encoding is inferred from the characters; three tests ask whether it looks like
uniform draws from that alphabet (chi-squared of the symbol counts, runs about
the median symbol, lag-one serial correlation). The likelihood ratio of uniform
draws against the corpus' own character frequencies is an e-value against the
hypothesis that a token is text; it grows with length, and counts as nothing where
the battery refuses the token. Over all candidates of one encoding and length
class, the e-values' form of Benjamini and Hochberg's step-up rule bounds the
expected share of false reports. The battery also judges the base matches' values.
"""

from __future__ import annotations

import hashlib
import math
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rowfold.llm.common import spans_text, staged, utf8

KINDS = ("assign", "access", "hex", "random")
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.IGNORECASE | re.ASCII)
WORDS = ("password", "passwd", "secret", "token", "apikey", "api_key")
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{24,}")
TOKEN = re.compile(r"[A-Za-z0-9+/_=-]{20,}")
#: Alphabets by name; the first that holds all characters of a token is its encoding.
ALPHABETS = {
    "decimal": "0123456789",
    "hex": "0123456789abcdef",
    "HEX": "0123456789ABCDEF",
    "base32": "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567",
    "base36": "0123456789abcdefghijklmnopqrstuvwxyz",
    "base62": "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789",
    "base64": "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/",
    "base64url": "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789-_",
}
_SETS = {k: frozenset(v) for k, v in ALPHABETS.items()}
_PLACE = {k: {c: i for i, c in enumerate(v)} for k, v in ALPHABETS.items()}
STEP = 0.25  # width of a bin of the log e-value


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(start, kind, end) of the three base patterns, each leftmost and non-overlapping."""
    out = []
    low = text.lower()
    if any(w in low for w in WORDS):
        out += [(m.start(), 0, m.end()) for m in ASSIGN.finditer(text) if len(m[2]) >= 6]
    if "AKIA" in text:
        out += [(m.start(), 1, m.end()) for m in ACCESS.finditer(text) if m.end() - m.start() >= 20]
    return out + [(m.start(), 2, m.end()) for m in HEX.finditer(text)]


def encoding_of(token: str) -> str | None:
    body = frozenset(token.rstrip("="))
    return next((k for k, v in _SETS.items() if body <= v), None)


PIECE = re.compile(r"[^=]+=*")


def parts(token: str) -> list[tuple[int, int]]:
    """(start, end) of the candidates of a token: itself if one encoding holds it, else in each piece between inner '='
    the parts of at least 20 characters that one encoding holds, the longest first where they overlap."""
    if encoding_of(token) is not None:
        return [(0, len(token))]
    out: list[tuple[int, int]] = []
    for p in PIECE.finditer(token):
        if p.end() - p.start() < 20:
            continue
        if encoding_of(p[0]) is not None:
            out.append(p.span())
            continue
        found = [m.span() for k in ("+/", "_-") for m in re.finditer(rf"[A-Za-z0-9{k}]{{20,}}=*", p[0])]
        own: list[tuple[int, int]] = []
        for s, e in sorted(found, key=lambda x: (x[0] - x[1], x[0])):
            if all(e <= a or s >= z for a, z in own):
                own.append((s, e))
        out += [(p.start() + s, p.start() + e) for s, e in own]
    return sorted(out)


def _normal_two_sided(z: float) -> float:
    return math.erfc(abs(z) / math.sqrt(2))


def battery(token: str, encoding: str) -> float:
    """Bonferroni-combined p-value of the three tests of uniformity, independence and lack of trend."""
    place, k = _PLACE[encoding], len(ALPHABETS[encoding])
    x = [place[c] for c in token.rstrip("=")]
    n = len(x)
    counts = [0] * k
    for v in x:
        counts[v] += 1
    chi = sum((c - n / k) ** 2 for c in counts) * k / n
    df = k - 1
    p_chi = 0.5 * math.erfc((((chi / df) ** (1 / 3) - (1 - 2 / (9 * df))) / math.sqrt(2 / (9 * df))) / math.sqrt(2))  # upper tail, cube-root normal form
    above = [v >= k / 2 for v in x]
    n1 = sum(above)
    n0 = n - n1
    runs = 1 + sum(a != b for a, b in zip(above, above[1:]))
    if n1 and n0:
        mean = 2 * n1 * n0 / n + 1
        var = (mean - 1) * (mean - 2) / max(1, n - 1)
        p_runs = _normal_two_sided((runs - mean) / math.sqrt(var)) if var > 0 else 1.0
    else:
        p_runs = 2.0 ** (1 - n)
    m = sum(x) / n
    var = sum((v - m) ** 2 for v in x)
    p_ser = _normal_two_sided((sum((a - m) * (b - m) for a, b in zip(x, x[1:])) / var + 1 / n) * math.sqrt(n)) if var else 0.0
    return min(1.0, 3 * min(p_chi, p_runs, p_ser))


def base_values(text: str) -> list[tuple[int, int, int, str]]:
    """(start, kind, end, value) of the base spans, in order; value is what would be secret."""
    out = []
    for s, k, e in sorted(base_spans(text)):
        out.append((s, k, e, ASSIGN.match(text, s, e)[2] if k == 0 else text[s:e]))
    return out


def base_p(values: list[str]) -> str:
    """The battery's p-values of values, comma-joined; '-' where no one encoding holds a value or it has no symbols."""
    out = []
    for v in values:
        enc = encoding_of(v) if v.rstrip("=") else None
        out.append("-" if enc is None else f"{battery(v, enc):.4f}")
    return ",".join(out)


def log_e(token: str, encoding: str, log_q: np.ndarray) -> float:
    """Log likelihood ratio of uniform draws from the encoding against the corpus' character frequencies."""
    body = token.rstrip("=")
    return -len(body) * math.log(len(ALPHABETS[encoding])) - float(sum(log_q[ord(c)] for c in body))


def candidates(text: str, taken: list[tuple[int, int, int]], log_q: np.ndarray, alpha: float) -> list[tuple]:
    """(start, end, stratum, bin, passes) of tokens that overlap no base span. bin: of the log e-value, 0 to 400."""
    out = []
    taken = sorted((s, e) for s, _, e in taken)
    at = 0
    for m in TOKEN.finditer(text):
        for s, e in ((m.start() + i, m.start() + z) for i, z in parts(m[0])):
            while at < len(taken) and taken[at][1] <= s:
                at += 1
            if at < len(taken) and taken[at][0] < e:
                continue
            token = text[s:e]
            enc = encoding_of(token)
            if enc is None or not token.rstrip("="):
                continue
            stratum = f"{enc}/{min(8, int(math.log2(e - s) * 2))}"
            ok = battery(token, enc) >= alpha
            out.append((s, e, stratum, max(0, min(400, int(log_e(token, enc, log_q) / STEP))), ok))
    return out


def char_counts(docs: DataFrame, text: str = "text") -> np.ndarray:
    """Byte counts of all texts: 256 sums, whatever the input's size."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(256, np.int64)
        for b in batches:
            raw, off = utf8(b.column(0))
            total += np.bincount(raw[off[0] : off[-1]], minlength=256)
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(256, dtype=np.int32)), pa.array(total)], names=["byte", "n"])

    got = docs.select(text).mapInArrow(count, "byte int, n long").groupBy("byte").agg(F.sum("n").alias("n")).collect()
    out = np.zeros(256, np.int64)
    for r in got:
        out[r["byte"]] = r["n"]
    return out


ROW = "base array<struct<start:int,kind:int,end:int>>, cand array<struct<start:int,end:int,stratum:string,bin:int,ok:boolean>>"


def find_secrets(docs: DataFrame, fdr: float = 0.01, alpha: float = 0.001, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per input row: id, n_assign, n_access, n_hex, base_sha256, spans, n_random, base_p.

    fdr: expected share of false reports among reported random tokens, held in each class of encoding and
    length; alpha: level at which the battery refuses a token. base_p: the battery's p-value of each base span's value,
    in order, '-' where it has no single encoding. A null text counts as empty (no spans); ids may
    be null or repeated; an empty table gives no rows; further columns are ignored. No text is cut.
    """
    n = char_counts(docs, text_col)
    log_q = np.log((n + 1) / (n.sum() + 256))

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out: dict[str, list] = {k: [] for k in ("n_assign", "n_access", "n_hex", "base_sha256", "base_p", "base", "cand")}
            for text in b.column(1).to_pylist():
                text = text or ""
                values = base_values(text)
                base = [v[:3] for v in values]
                out["base_p"].append(base_p([v[3] for v in values]))
                for i, k in enumerate(("n_assign", "n_access", "n_hex")):
                    out[k].append(sum(x[1] == i for x in base))
                out["base_sha256"].append(hashlib.sha256(spans_text(base, KINDS).encode()).hexdigest())
                out["base"].append([dict(zip(("start", "kind", "end"), x)) for x in base])
                out["cand"].append([dict(zip(("start", "end", "stratum", "bin", "ok"), x)) for x in candidates(text, base, log_q, alpha)])
            kinds = [pa.int64()] * 3 + [pa.string()] * 2 + [pa.list_(pa.struct([("start", pa.int32()), ("kind", pa.int32()), ("end", pa.int32())])), pa.list_(pa.struct([("start", pa.int32()), ("end", pa.int32()), ("stratum", pa.string()), ("bin", pa.int32()), ("ok", pa.bool_())]))]
            yield pa.RecordBatch.from_arrays([b.column(0), *(pa.array(v, t) for v, t in zip(out.values(), kinds))], names=[id_col, *out])

    src = docs.select(id_col, text_col)
    found = staged(src.mapInArrow(scan, f"{id_col} {dict(src.dtypes)[id_col]}, n_assign long, n_access long, n_hex long, base_sha256 string, base_p string, {ROW}"), "secrets")
    cut = fdr_cuts(found.select(F.explode("cand").alias("c")).select("c.*"), fdr)
    passing = F.filter("cand", lambda c: c["ok"] & F.coalesce(c["bin"] >= F.try_element_at(cut, c["stratum"]), F.lit(False))) if cut is not None else F.filter("cand", lambda c: F.lit(False))
    own = found.withColumn("new", F.transform(passing, lambda c: F.struct(c["start"].alias("start"), F.lit(3).alias("kind"), c["end"].alias("end"))))
    names = F.array(*map(F.lit, KINDS))
    spans = F.transform(F.array_sort(F.concat("base", "new")), lambda x: F.concat_ws(":", F.get(names, x["kind"]), x["start"].cast("string"), x["end"].cast("string")))
    return own.select(id_col, "n_assign", "n_access", "n_hex", "base_sha256", F.concat_ws(",", spans).alias("spans"), F.size("new").cast("long").alias("n_random"), "base_p")


def fdr_cuts(cand: DataFrame, fdr: float):
    """A map column from stratum to the least bin that is reported, or None without candidates.

    Among the m candidates of a stratum, the k of largest e-values are reported for the largest k of which each has at
    least m / (fdr k); those that the battery refuses have an e-value of 0, so they count in m and never in k. Bins are
    at most 401 for each of at most 72 strata, so the table that comes to the driver is bounded.
    """
    bins = cand.groupBy("stratum", "bin").agg(F.count("*").alias("n"), F.sum(F.col("ok").cast("long")).alias("n_ok")).collect()
    total: dict[str, int] = {}
    for r in bins:
        total[r["stratum"]] = total.get(r["stratum"], 0) + r["n"]
    cuts, seen = {}, {}
    for r in sorted(bins, key=lambda r: -r["bin"]):
        k = r["stratum"]
        seen[k] = seen.get(k, 0) + r["n_ok"]
        if seen[k] and math.exp(r["bin"] * STEP) >= total[k] / (fdr * seen[k]):
            cuts[k] = r["bin"]
    return F.create_map(*[F.lit(x) for kv in sorted(cuts.items()) for x in kv]) if cuts else None
