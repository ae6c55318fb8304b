"""Personal data: base patterns, and identifiers found by bootstrapped contexts.

Base matches are seeds. Every seed, and every other identifier-like token, gives
edges to the instance from lexical patterns (words beside it, with its shape and
without) and from its shape alone. A shape adds to the weight of an instance, but
only words beside it can name one, whatever its own shape.
Scores pass over this bipartite graph a few times: a pattern is as good as the
share of its instances that are trusted, an instance as good as its patterns
together. Patterns that end with high confidence and enough support name the
unseen instances that stand in them.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rowfold.llm.common import spans_text, staged

KINDS = ("email", "ip", "card", "phone")
LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
DOTTED = re.compile(r"[0-9][0-9.]*")
IP = re.compile(r"(?<![0-9])[0-9]++(?:\.[0-9]++){3}")
CARD = re.compile(r"[0-9](?:[ -]?[0-9])+")
PHONE = re.compile(r"\+[0-9][ ().0-9-]+[0-9]")
LIKE = re.compile(r"\S*[0-9@]\S*")
GROUPS = re.compile(r"(?<!\S)[(+]*[0-9][0-9().+/-]*(?: [(+]*[0-9][0-9().+/-]*)+")  # numbers that one blank parts
EDGE = " \t\r\n.,;:!?\"'()[]{}<>*#$%&|"
WORD_BEFORE = re.compile(r"(\S+)\s+$")
WORD_AFTER = re.compile(r"\s*(\S+)")
REACH = 80  # characters beside an instance in which its neighbour words are sought


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = int(c) * (1 + i % 2)
        total += d - 9 * (d > 9)
    return total % 10 == 0


def emails(text: str) -> list[tuple[int, int, int]]:
    """Leftmost non-overlapping e-mails, found from each @ outwards so that long runs cost no rescans."""
    out, done, at = [], 0, text.find("@")
    while at >= 0:
        s = at
        while s > done and text[s - 1] in LOCAL:
            s -= 1
        m = DOMAIN.match(text, at + 1) if s < at else None
        if m:
            done = m.end()
            out.append((s, 0, done))
        at = text.find("@", max(at + 1, done))
    return out


def ips(text: str) -> list[tuple[int, int, int]]:
    out = []
    for run in DOTTED.finditer(text):
        if run.end() - run.start() >= 7 and run[0].count(".") >= 3:
            out += [(m.start(), 1, m.end()) for m in IP.finditer(text, run.start(), run.end()) if all(len(p := x.lstrip("0")) <= 3 and int(p or 0) <= 255 for x in m[0].split("."))]
    return out


def cards(text: str) -> list[tuple[int, int, int]]:
    out = []
    for m in CARD.finditer(text):
        if m.end() - m.start() >= 12:
            d = m[0].replace(" ", "").replace("-", "")
            if 12 <= len(d) <= 19 and luhn(d):
                out.append((m.start(), 2, m.end()))
    return out


def phones(text: str) -> list[tuple[int, int, int]]:
    return [(m.start(), 3, m.end()) for m in PHONE.finditer(text) if 9 <= sum("0" <= c <= "9" for c in m[0]) <= 15] if "+" in text else []


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(start, kind, end) of the base patterns, in order."""
    return sorted(emails(text) + ips(text) + cards(text) + phones(text))


def short(s: str) -> str:
    """The string, or its hash where it is long."""
    return s if len(s) <= 64 else hashlib.sha256(s.encode()).hexdigest()


def shape(s: str) -> str:
    """Digits become 9, letters a; runs of letters become one, runs of digits keep their length."""
    return short(re.sub(r"a+", "a", "".join("9" if c.isdigit() else "a" if c.isalpha() else c for c in s)))


def patterns(text: str, s: int, e: int) -> list[str]:
    """The lexical patterns in which the instance [s, e) stands: word before, word after, both; each with its shape and
    without. Last its shape alone."""
    b = WORD_BEFORE.search(text[max(0, s - REACH) : s])
    a = WORD_AFTER.match(text[e : e + REACH])
    left, right, form = (b[1].lower() if b else "^"), (a[1].lower() if a else "$"), shape(text[s:e])
    beside = [f"{left} _", f"_ {right}", f"{left} _ {right}"]
    return [*(f"{x} | {form}" for x in beside), *beside, f"| {form}"]


def instances(text: str, base: list[tuple[int, int, int]]) -> list[tuple[int, int]]:
    """Identifier-like tokens beside the base spans, and groups of numbers that single blanks part: at least five
    characters with three digits or an @."""
    out, at = [], 0
    taken = [(s, e) for s, _, e in base]
    for s, e in sorted({m.span() for k in (LIKE, GROUPS) for m in k.finditer(text)}):
        while s < e and text[s] in EDGE:
            s += 1
        while e > s and text[e - 1] in EDGE:
            e -= 1
        if e - s < 5:
            continue
        while at < len(taken) and taken[at][1] <= s:
            at += 1
        if any(x < e for x, _ in taken[at : at + 1]):
            continue
        if sum(c.isdigit() for c in text[s:e]) >= 3 or "@" in text[s:e]:
            out.append((s, e))
    return sorted(set(out))


SPAN = pa.struct([("start", pa.int32()), ("kind", pa.int32()), ("end", pa.int32())])
CAND = pa.struct([("start", pa.int32()), ("end", pa.int32()), ("kind", pa.int32()), ("value", pa.string()), ("patterns", pa.list_(pa.string()))])


def _extract(batches: Iterator[pa.RecordBatch], id_col: str) -> Iterator[pa.RecordBatch]:
    names = [*(f"n_{k}" for k in KINDS), "base_sha256", "base", "cand"]
    kinds = [pa.int64()] * 4 + [pa.string(), pa.list_(SPAN), pa.list_(CAND)]
    for b in batches:
        out: dict[str, list] = {k: [] for k in names}
        for text in b.column(1).to_pylist():
            text = text or ""
            base = base_spans(text)
            for i, k in enumerate(KINDS):
                out[f"n_{k}"].append(sum(x[1] == i for x in base))
            out["base_sha256"].append(hashlib.sha256(spans_text(base, KINDS).encode()).hexdigest())
            out["base"].append([{"start": s, "kind": k, "end": e} for s, k, e in base])
            seen = [(s, e, k) for s, k, e in base] + [(s, e, -1) for s, e in instances(text, base)]
            out["cand"].append([{"start": s, "end": e, "kind": k, "value": short(text[s:e].lower()), "patterns": patterns(text, s, e)} for s, e, k in seen])
        yield pa.RecordBatch.from_arrays([b.column(0), *(pa.array(v, t) for v, t in zip(out.values(), kinds))], names=[id_col, *names])


def score_patterns(edges: DataFrame, rounds: int = 3, trust: float = 0.5) -> DataFrame:
    """edges (pattern, value, kind; kind -1 for no seed) to (pattern, kind, conf, support).

    conf = trusted weight / (instances + 1). A value that seeds show with a kind has weight 1 for it; others
    get, in each round, 1 minus the product of (1 - conf) over their patterns, where that reaches `trust`.
    """
    e = edges.groupBy("pattern", "value").agg(F.max("kind").alias("kind"))  # copies of one text count once
    e = staged(e, "pii-edges")
    size = e.groupBy("pattern").agg(F.count("*").alias("n"))
    weight = e.filter("kind >= 0").select("value", "kind").distinct().withColumn("w", F.lit(1.0))
    seeds, score = weight, None
    bare = e.select("pattern", "value")
    for i in range(rounds + 1):
        by_kind = bare.join(weight, "value").groupBy("pattern", "kind").agg(F.round(F.sum("w"), 6).alias("support"))
        score = by_kind.join(size, "pattern").select("pattern", "kind", "support", F.round(F.col("support") / (F.col("n") + 1), 6).alias("conf"))
        if i == rounds:
            break
        score = score.filter("conf > 0.05 and support >= 2")
        got = bare.join(score, "pattern").groupBy("value", "kind").agg(F.round(1 - F.exp(F.sum(F.log1p(-F.col("conf")))), 6).alias("w")).filter(F.col("w") >= trust)
        weight = staged(got.join(seeds.select("value"), "value", "left_anti").select("value", "kind", "w").unionByName(seeds), f"pii-weights{i}")
    return score


def find_pii(docs: DataFrame, min_conf: float = 0.6, min_support: float = 3.0, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per input row: id, n_email, n_ip, n_card, n_phone (base matches), base_sha256, spans, n_found.

    min_conf and min_support: what a pattern needs to name unseen identifiers. A null text counts as empty; ids
    may be null or repeated; an empty table gives no rows; further columns are ignored. Where several promoted
    patterns claim a token, the most confident wins, then the lower kind.
    """
    src = docs.select(id_col, text_col)
    schema = f"{id_col} {dict(src.dtypes)[id_col]}, n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, base array<struct<start:int,kind:int,end:int>>, cand array<struct<start:int,end:int,kind:int,value:string,patterns:array<string>>>"
    rows = src.mapInArrow(lambda it: _extract(it, id_col), schema).withColumn("row", F.monotonically_increasing_id())
    rows = staged(rows, "pii-rows")
    cand = rows.select("row", F.explode("cand").alias("c")).select("row", "c.*")
    edges = cand.select("value", "kind", F.explode("patterns").alias("pattern"))
    promoted = score_patterns(edges).filter(~F.col("pattern").startswith("| ")).filter((F.col("conf") >= min_conf) & (F.col("support") >= min_support))
    best = promoted.groupBy("pattern").agg(F.max(F.struct("conf", (-F.col("kind")).alias("k"))).alias("b")).select("pattern", F.col("b.conf").alias("conf"), (-F.col("b.k")).alias("kind"))
    named = cand.filter("kind < 0").select("row", "start", "end", F.explode("patterns").alias("pattern")).join(best, "pattern")
    named = named.groupBy("row", "start", "end").agg(F.max(F.struct("conf", (-F.col("kind")).alias("k"))).alias("b")).select("row", F.struct("start", (-F.col("b.k")).alias("kind"), "end").alias("s"))
    new = named.groupBy("row").agg(F.collect_list("s").alias("new"))  # the spans of one text
    none = F.array().cast("array<struct<start:int,kind:int,end:int>>")
    names = F.array(*map(F.lit, KINDS))
    inner = lambda x: F.exists("new", lambda y: (y["start"] <= x["start"]) & (y["end"] >= x["end"]) & (y["end"] - y["start"] > x["end"] - x["start"]))
    new = new.withColumn("new", F.filter("new", lambda x: ~inner(x)))  # a number within a named group
    out = rows.drop("cand").join(new, "row", "left").withColumn("new", F.coalesce("new", none))
    spans = F.transform(F.array_sort(F.concat("base", "new")), lambda x: F.concat_ws(":", F.get(names, x["kind"]), x["start"].cast("string"), x["end"].cast("string")))
    return out.select(id_col, *(f"n_{k}" for k in KINDS), "base_sha256", F.concat_ws(",", spans).alias("spans"), F.size("new").cast("long").alias("n_found"))


def without_spans(text: str, spans: str) -> str:
    """The text with every span replaced by its kind in angle brackets; of overlapping spans the union, by the first's kind."""
    out, at, done = [], 0, -1
    for kind, s, e in (x.split(":") for x in spans.split(",")):
        if int(s) >= done:
            out += [text[at : int(s)], f"<{kind}>"]
        done = at = max(at, int(e))
    return "".join([*out, text[at:]])


def redacted(docs: DataFrame, text_col: str = "text", size_col: str = "n_chars") -> DataFrame:
    """docs with a column `spans` (as find_pii gives them, or null), without their spans; the length column follows the text.
    Rows without spans stay as they are."""
    at, size, spans = (docs.columns.index(c) for c in (text_col, size_col, "spans"))

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            hit = pc.is_valid(b.column(spans)).to_numpy(zero_copy_only=False)
            cols = list(b.columns)
            if hit.any():
                found = b.column(spans).to_pylist()
                texts = [without_spans(t or "", s) if s else t for t, s in zip(b.column(at).to_pylist(), found)]
                n = [len(t) if s else k for t, s, k in zip(texts, found, b.column(size).to_pylist())]
                cols[at], cols[size] = pa.array(texts, pa.string()), pa.array(n, b.schema.field(size).type)
            yield pa.RecordBatch.from_arrays(cols, names=b.schema.names)

    return docs.mapInArrow(work, ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema))
