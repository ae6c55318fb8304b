"""The training-data operators against brute force on small tables that hold nulls, empty and long texts, ties, repeated
rows, further columns and nothing at all."""

import hashlib
import math
import random
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from rowfold.llm import columnwise, decontaminate, jaccard, kneser_ney, pieces, pii, quality, secrets, sharding, shingles, substring_dedup, token_counts, topk

MODEL = "/opt/tokenizers/piece_bpe_32k.model"
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, part int, size string, node string, w double"


def prose(rng, n, stock=None):
    stock = stock or ["".join(rng.choice(["th", "er", "on", "an", "ing", "re", "st", "ou", "le"]) for _ in range(rng.randint(1, 4))) for _ in range(400)]
    return " ".join(rng.choice(stock) for _ in range(n))


def texts(seed=0):
    rng = random.Random(seed)
    out = [None, "", " \t\n ", "one", "One", "two words", "a b c d", "a b c d e", "x" * 5000, "é" * 60 + " ß ñ", "ab " * 400, "!!!!" * 30]
    base = [prose(rng, rng.randint(30, 160)) for _ in range(12)]
    out += base
    for b in base[:6]:
        w = b.split()
        out += [b, b]  # copies
        for k in (1, 2, 8):
            v = list(w)
            for _ in range(k):
                v[rng.randrange(len(v))] = "changed"
            out.append(" ".join(v))
    shared = prose(rng, 25)
    out += [prose(rng, 20) + " " + shared + " " + prose(rng, 20) for _ in range(6)] + [shared[:60], shared[10:61]]
    rng.shuffle(out)
    return out


def frame(spark, rows, parts=5):
    data = [(i, t, "en" if (i or 0) % 3 else None, "s", len(t or ""), 7, "clash", "clash", 0.5) for i, t in rows]
    return spark.createDataFrame(data, SCHEMA).repartition(parts)


@pytest.fixture(scope="module")
def rows():
    return list(enumerate(texts()))


@pytest.fixture(scope="module")
def docs(spark, rows):
    return frame(spark, rows).persist()


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


# 2 ---------------------------------------------------------------------------------------------------------------------


def test_shards(spark, docs, rows, empty):
    got = sorted(sharding.shard_by_bytes(docs, 4).collect(), key=lambda r: r["doc_id"])
    at, total = 0, sum(len((t or "").encode()) + 1 for _, t in rows)
    slots = Counter()
    for r, (i, t) in zip(got, rows):
        b = (t or "").encode()
        s = at * 4 // total
        assert (r["doc_id"], r["size"], r["text_crc32"], r["shard"], r["slot"], r["law"], r["grown_shard"]) == (i, len(b) + 1, zlib.crc32(b), s, slots[s], "bytes", None)
        slots[s] += 1
        at += len(b) + 1
    assert sharding.shard_by_bytes(empty, 4).count() == 0
    twice = frame(spark, [(1, "a"), (1, "a"), (None, "b"), (2, None)])
    assert sorted(r["slot"] for r in sharding.shard_by_bytes(twice, 1).collect()) == [0, 1, 2, 3]


# 3 ---------------------------------------------------------------------------------------------------------------------


def repeats_brute(rows, length=50):
    by = defaultdict(list)
    for i, t in rows:
        by[-(1 << 63) if i is None else i].append((t or "").encode())
    seen, out = set(), []
    for i in sorted(by):
        for b in by[i]:
            gone = bytearray(len(b))
            for k in range(len(b) - length + 1):
                if b[k : k + length] in seen:
                    gone[k : k + length] = b"\1" * length
            g = bytes(gone)
            out.append((None if i == -(1 << 63) else i, len(b), sum(g), sum(1 for k in range(len(g)) if g[k] and (k == 0 or not g[k - 1])), hashlib.sha256(bytes(x for x, y in zip(b, g) if not y)).hexdigest()))
        for b in by[i]:
            seen |= {b[k : k + length] for k in range(len(b) - length + 1)}
    return sorted(out, key=str)


def test_substring_dedup(spark, docs, rows, empty):
    cols = ("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256")
    got = lambda df: sorted((tuple(r[c] for c in cols) for r in substring_dedup.remove_repeats(df).collect()), key=str)
    assert got(docs) == repeats_brute(rows)
    odd = [(1, "q" * 300), (2, "q" * 120 + "z"), (2, "q" * 120 + "z"), (None, "q" * 49), (None, "z" * 50 + "q" * 60), (5, "z" * 80)]
    assert got(frame(spark, odd)) == repeats_brute(odd)
    assert got(empty) == []


def test_suffix_order_in_memory_and_in_files(tmp_path):
    rng = random.Random(5)
    for _ in range(40):
        s = [bytes(rng.choice(b"ab") for _ in range(rng.randint(0, 12))) for _ in range(rng.randint(1, 7))]
        data, ends = np.frombuffer(b"".join(s), np.uint8), np.cumsum([len(x) for x in s])
        a, b = columnwise.suffix_order(data, ends), columnwise.suffix_order(data, ends, in_memory=0, folder=f"file://{tmp_path}")
        assert all((x == y).all() for x, y in zip(a, b)) and not list(tmp_path.iterdir())
        suffixes = [s[i][k:] for i, k in zip(a[2], a[3])]
        assert suffixes == sorted(suffixes) and len(suffixes) == sum(len(x) + 1 for x in s)
        for n in range(1, len(suffixes)):
            x, y = suffixes[n - 1], suffixes[n]
            assert a[1][n] == next((k for k in range(min(len(x), len(y))) if x[k] != y[k]), min(len(x), len(y)))
        assert all(a[0][n] == (s[i][k - 1] + 1 if k else 0) for n, (i, k) in enumerate(zip(a[2], a[3])))


# 4 ---------------------------------------------------------------------------------------------------------------------

EMAIL = re.compile(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+")
IP = re.compile(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)")
CARD = re.compile(r"[0-9]([\x20-]?[0-9])+")
PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")


def pii_brute(t):
    out = [(m.start(), 0, m.end()) for m in EMAIL.finditer(t)]
    out += [(m.start(), 1, m.end()) for m in IP.finditer(t) if all(int(p) <= 255 for p in m[0].split("."))]
    for m in CARD.finditer(t):
        d = re.sub("[^0-9]", "", m[0])
        if 12 <= len(d) <= 19 and sum((int(c) * 2 - 9 * (int(c) > 4)) if k % 2 else int(c) for k, c in enumerate(reversed(d))) % 10 == 0:
            out.append((m.start(), 2, m.end()))
    return sorted(out + [(m.start(), 3, m.end()) for m in PHONE.finditer(t) if 9 <= len(re.sub("[^0-9]", "", m[0])) <= 15])


def pii_texts():
    rng = random.Random(9)
    bits = ["a.b@c.de", "x@y", "@@", "a@b.c%d@e.f", "1.2.3.4", "256.1.1.1", "1.2.3.4.5.6.7.8", "000001.2.3.4", "4111 1111 1111 1111", "4111-1111-1111-1112", "+1 (555) 123-4567", "+1", "++49 30 123456", "12-34", "9" * 40, "a" * 30 + "@b.co", ".", " ", "ü", "-", "1", "@", "+"]
    return ["".join(rng.choice(bits) for _ in range(rng.randint(1, 9))) for _ in range(300)]


def test_pii_base_spans():
    for t in pii_texts():
        assert pii.base_spans(t) == pii_brute(t), t


def test_pii_contexts_find_unseen_identifiers(spark, empty):
    rng = random.Random(4)
    rows = [(i, f"{prose(rng, 8)} card: {n} end {prose(rng, 5)}") for i, n in enumerate(["4111111111111111", "5500005555555559", "4012888888881881", "6011000990139424", "3530111333300000"] * 2)]
    rows += [(100, f"{prose(rng, 6)} card: 4111111111111112 end of it"), (101, f"{prose(rng, 6)} item 4111111111111112 of"), (102, None), (103, ""), (104, "x" * 9000), (104, "x" * 9000)]
    got = {r["doc_id"]: r for r in pii.find_pii(frame(spark, rows)).collect()}
    assert got[0]["n_card"] == 1 and got[100]["n_card"] == 0
    t = dict(rows)[100]
    a = t.index("4111")
    assert got[100]["spans"] == f"card:{a}:{a + 16}" and got[100]["n_found"] == 1
    assert got[101]["spans"] == "" and got[102]["spans"] == "" and len(got) == 15
    assert got[0]["base_sha256"] == hashlib.sha256(got[0]["spans"].encode()).hexdigest()
    assert pii.find_pii(empty).count() == 0


def test_pii_contexts_find_identifiers_of_shapes_without_seeds(spark):
    rng = random.Random(15)
    cards = ["4111111111111111", "5500005555555559", "4012888888881881", "6011000990139424", "3530111333300000", "5105105105105100"]
    rows = [(i, f"{prose(rng, 8)} card: {n} end {prose(rng, 5)}") for i, n in enumerate(cards)]
    new = ["4111-11111-11111-1112", "078 05 1120", "9" + "ab1" * 30]
    rows += [(100 + i, f"{prose(rng, 6)} card: {n} {prose(rng, 5)}") for i, n in enumerate(new)] + [(110, f"{prose(rng, 6)} item {new[0]} {prose(rng, 5)}")]
    got = {r["doc_id"]: r["spans"] for r in pii.find_pii(frame(spark, rows)).collect()}
    for i, n in enumerate(new):
        a = dict(rows)[100 + i].index(n)
        assert got[100 + i] == f"card:{a}:{a + len(n)}"
    assert got[110] == ""


# 5, 9 ------------------------------------------------------------------------------------------------------------------


def test_pieces_round_trip_and_best_score(spark, docs, rows, empty):
    p = pieces.load_pieces(MODEL)
    got = {r["doc_id"]: r for r in pieces.encode(docs, MODEL).collect()}
    assert all(r["exact"] for r in got.values()) and len(got) == len(rows)
    assert got[next(i for i, t in rows if t is None)]["ids"] == []
    odd = frame(spark, [(1, "▁a ▁ b  c "), (2, " "), (3, "日本 😀\n\t"), (4, "w" * 700 + "é" * 90), (None, "x"), (1, "y")])
    e = pieces.encode(odd, MODEL)
    assert all(r["exact"] for r in e.collect())
    back = {(r["doc_id"], r["text"]) for r in pieces.decode(e, MODEL).collect()}
    assert back == {(r["doc_id"], r["text"]) for r in odd.collect()}
    assert pieces.encode(empty, MODEL).count() == 0
    score = {}
    for k, i in zip(p.keys.tolist(), range(len(p.keys))):
        score[k] = p.scores[i]
    words = sorted({w for _, t in rows if t for w in t.split(" ")})[:150] + ["zq" * 40]
    ids, counts = pieces.encode_words(words, p)
    place = {int(v): i for i, v in enumerate(p.ids)}
    at = 0
    for w, n in zip(words, counts):
        own, at = ids[at : at + n], at + n
        full = pieces.MARK + w
        best = [0.0] + [-math.inf] * len(full)
        for j in range(1, len(full) + 1):
            for k in range(1, min(p.longest, j) + 1):
                s = score.get(int(pieces.hash_of(full[j - k : j])) * int(pieces.SPREAD) % (1 << 64))
                v = best[j - k] + s if s is not None else best[j - 1] + p.unknown if k == 1 else -math.inf
                best[j] = max(best[j], v)
        if not set(own.tolist()) & set(p.byte_ids.tolist()):
            assert sum(p.scores[place[int(i)]] for i in own) == pytest.approx(best[-1])


def test_probe_of_sorted_hashes():
    p = pieces.load_pieces(MODEL)
    back = np.uint64(pow(int(pieces.SPREAD), -1, 1 << 64))
    some = np.random.default_rng(0).integers(0, 1 << 63, 200_000, dtype=np.uint64)
    at, found = pieces.probe(p, np.concatenate([p.keys * back, some]))
    assert p.run < 16 and (np.diff(p.keys.astype(object)) > 0).all()
    assert found[: len(p.keys)].all() and (at[: len(p.keys)] == np.arange(len(p.keys))).all()
    assert (found[len(p.keys) :] == np.isin(some * pieces.SPREAD, p.keys)).all()


def test_pieces_of_runs_of_blanks_have_the_best_score_of_the_whole_vocabulary():
    import sentencepiece

    sp = sentencepiece.SentencePieceProcessor(model_file=MODEL)
    p = pieces.load_pieces(MODEL)
    score = {sp.id_to_piece(i): sp.get_score(i) for i in range(sp.get_piece_size()) if not (sp.is_byte(i) or sp.is_control(i) or sp.is_unknown(i))}
    texts = ["a" + " " * 8 + "b", "  if x:\n        y = 1", "a  b   c ", "   ", " a", "w" + " " * 90 + "z  ", "plain text here"]
    ids, counts = pieces.encode_batch(pa.array(texts), p)
    raw, off = pieces.decode_batch(ids, counts, p)
    assert [raw[off[i] : off[i + 1]].tobytes().decode() for i in range(len(texts))] == texts
    upto = np.concatenate([[0], np.cumsum(counts)])
    for i, t in enumerate(texts):
        own = ids[upto[i] : upto[i + 1]].tolist()
        if set(own) & set(p.byte_ids.tolist()):
            continue
        full = pieces.MARK + t.replace(" ", pieces.MARK)
        best = [0.0] + [-math.inf] * len(full)
        for j in range(1, len(full) + 1):
            best[j] = max(best[j - k] + score.get(full[j - k : j], -math.inf) for k in range(1, min(p.longest, j) + 1))
        assert sum(sp.get_score(v) for v in own) == pytest.approx(best[-1], rel=1e-12)
    assert len(ids[: counts[0]]) == 3


def test_token_counts(spark, docs, empty):
    flat = token_counts.write_flat(docs, MODEL, block_tokens=97)  # blocks that cut documents
    counts = token_counts.count_tokens(flat.filter("kind = 'tokens'").select("stream", "block", "data"))
    got = {r["doc_id"]: r["n_tokens"] for r in token_counts.documents_of(flat.filter("kind = 'order'")).join(counts, ["stream", "ordinal"]).collect()}
    want = {r["doc_id"]: r["n_pieces"] for r in pieces.encode(docs, MODEL).collect()}
    assert got == want
    assert {r["doc_id"]: r["n_tokens"] for r in token_counts.tokens_by_document(docs, MODEL).collect()} == want
    assert token_counts.tokens_by_document(empty, MODEL).count() == 0


def test_flat_files(spark, tmp_path):
    rng = np.random.default_rng(0)
    tokens = rng.integers(3, 100, 5000).astype("<u2")
    tokens[rng.integers(0, 5000, 60)] = 2
    tokens[-1] = 9  # an unfinished document
    (tmp_path / "a.bin").write_bytes(tokens.tobytes())
    (tmp_path / "b.bin").write_bytes(np.array([2, 2, 5, 2], "<u2").tobytes())
    got = token_counts.count_tokens(token_counts.read_flat_files(spark, str(tmp_path), 514).select("stream", "block", "data")).orderBy("stream", "ordinal").collect()
    ends = np.append(np.flatnonzero(tokens == 2), len(tokens))
    assert [r["n_tokens"] for r in got if r["stream"] == 0] == (np.diff(ends, prepend=-1) - 1).tolist()
    assert [r["n_tokens"] for r in got if r["stream"] == 1] == [0, 0, 1]


# 6 ---------------------------------------------------------------------------------------------------------------------


def jaccard_brute(rows):
    low = str.maketrans({chr(c): chr(c + 32) for c in range(65, 91)})
    sets = []
    for _, t in rows:
        w = re.findall(r"[^\x20\x09-\x0D]+", (t or "").translate(low))
        sets.append({tuple(w[i : i + 5]) for i in range(len(w) - 4)} if len(w) >= 5 else {tuple(w)} if w else set())
    up = list(range(len(rows)))

    def top(x):
        while up[x] != x:
            x = up[x]
        return x

    for i in range(len(rows)):
        for j in range(i):
            n = len(sets[i] & sets[j])
            if sets[i] and sets[j] and 100 * n >= 80 * (len(sets[i]) + len(sets[j]) - n):
                up[max(top(i), top(j))] = min(top(i), top(j))
    least = defaultdict(lambda: math.inf)
    for x, (i, _) in enumerate(rows):
        least[top(x)] = min(least[top(x)], i)
    return sorted((i, len(s), least[top(x)] if s else i) for x, ((i, _), s) in enumerate(zip(rows, sets)))


@pytest.mark.parametrize("frequent,wide", [(512, 24), (3, 24), (3, 2), (2, 6)])
def test_jaccard(spark, monkeypatch, frequent, wide, empty):
    monkeypatch.setattr(jaccard, "FREQUENT", frequent)
    monkeypatch.setattr(jaccard, "WIDE", wide)
    monkeypatch.setattr(jaccard, "GROUP", 512 if wide == 24 else 2)  # small groups: many cells a key
    monkeypatch.setattr(jaccard, "MANY", 1000 if wide == 24 else 3)
    rng = random.Random(frequent * 10 + wide)
    rows = texts(frequent + wide)
    base = prose(rng, 60).split()
    for _ in range(25):  # a cloud of near copies
        v = list(base)
        for _ in range(rng.randint(0, 4)):
            v[rng.randrange(len(v))] = rng.choice(["p", "q", "r"])
        rows.append(" ".join(v[rng.randint(0, 3) :]))
    rows = list(enumerate(rows))
    got = sorted(tuple(r) for r in jaccard.jaccard_groups(frame(spark, rows)).collect())
    assert got == jaccard_brute(rows)
    if wide == 6:
        assert jaccard.jaccard_groups(empty).count() == 0


def test_shingle_words_split_like_the_pattern():
    t = ["A b\tc\x0b d\x0ce", "é\xa0x y", "", "  ", "q"]
    a = pa.array(t)
    from rowfold.llm.common import utf8

    _, _, n = shingles.words(*utf8(a))
    assert n.tolist() == [len(re.findall(r"[^\x20\x09-\x0D]+", x)) for x in t]


# 7 ---------------------------------------------------------------------------------------------------------------------

ASSIGN = re.compile(r"""(?i:(password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.ASCII)


def test_secrets_base_and_random(spark, empty):
    rng = random.Random(3)
    bits = ["password", "TOKEN", "api_key", "apikey", "=", ":", " ", '"', "'", "abc", "abcdef12", "AKIA", "AKIA" + "Z9" * 9, "0123456789abcdef" * 2, "f" * 23, "ſecret=abcdefgh", "\n"]
    cases = ["".join(rng.choice(bits) for _ in range(rng.randint(1, 10))) for _ in range(300)]
    for t in cases:
        want = [(m.start(), 0, m.end()) for m in ASSIGN.finditer(t) if len(m[2]) >= 6]
        want += [(m.start(), 1, m.end()) for m in re.finditer(r"AKIA[A-Z0-9]+", t) if len(m[0]) >= 20]
        want += [(m.start(), 2, m.end()) for m in re.finditer(r"[0-9a-f]+", t) if len(m[0]) >= 24]
        assert sorted(secrets.base_spans(t)) == sorted(want), t
    alphabet = secrets.ALPHABETS["base62"]
    keys = ["".join(rng.choice(alphabet) for _ in range(40)) for _ in range(20)]
    rows = [(i, f"{prose(rng, 200)} {k} {prose(rng, 20)}") for i, k in enumerate(keys)] + [(50, prose(rng, 100) + " " + "the" * 12 + " ABABABABABABABABABABABAB"), (51, None), (52, "")]
    got = {r["doc_id"]: r for r in secrets.find_secrets(frame(spark, rows)).collect()}
    assert sum(got[i]["n_random"] for i in range(20)) >= 19
    assert got[50]["n_random"] == 0 and got[51]["spans"] == "" and len(got) == 23
    assert secrets.find_secrets(empty).count() == 0


def test_secrets_within_assignments_paths_and_digits():
    rng = random.Random(14)
    draw = lambda k, n: "".join(rng.choice(secrets.ALPHABETS[k]) for _ in range(n))
    key, pat, num = draw("base64", 39) + "A", draw("base62", 36), draw("decimal", 60)
    log_q = np.full(256, math.log(1 / 200))
    for before, secret in (("aws_secret_access_key=", key), ("GITHUB_PAT=", "ghp_" + pat), ("?sig=", pat + "=="), ("id: ", num), ("a_b-c=", num)):
        t = f"see {before}{secret} end"
        at = t.index(secret)
        got = secrets.candidates(t, [], log_q, 0.001)
        assert (at, at + len(secret)) in [x[:2] for x in got], t
    t = "my-long_path-name/" + pat
    assert any(s <= t.index(pat) and e == len(t) for s, e, *_ in secrets.candidates(t, [], log_q, 0.001))
    assert secrets.candidates("x " + num, [], log_q, 0.0)[0][2].startswith("decimal/")


def test_unseen_secrets_are_found_and_prose_is_not(spark):
    """Planted keys of five encodings and three lengths: the share found, and no word of prose reported."""
    rng = random.Random(21)
    rows, planted = [], {}
    for i in range(300):
        enc = ("HEX", "base32", "base62", "base64", "base64url")[i % 5]
        key = "".join(rng.choice(secrets.ALPHABETS[enc]) for _ in range((32, 40, 64)[i % 3]))
        rows.append((i, f"{prose(rng, 30)} key {key} {prose(rng, 30)}"))
        planted[i] = key
    rows += [(1000 + i, prose(rng, 40) + " " + "".join(prose(rng, 9).split()) + " " + "ab" * 16 + " " + prose(rng, 9).replace(" ", "-")) for i in range(300)]
    got = {r["doc_id"]: r for r in secrets.find_secrets(frame(spark, rows)).collect()}
    whole = [i for i, key in planted.items() if f"random:{dict(rows)[i].index(key)}:{dict(rows)[i].index(key) + len(key)}" in got[i]["spans"]]
    assert len(whole) >= 0.95 * len(planted)
    assert sum(got[1000 + i]["n_random"] for i in range(300)) <= 3


def test_battery_judges_base_values(spark):
    rng = random.Random(2)
    hexes = "".join(rng.choice("0123456789abcdef") for _ in range(40))
    rows = [(0, f"password = zzzzzzzzzzzzzzzzzzzzzzzzzzzz and {hexes}"), (1, "token: ......"), (2, "nothing")]
    got = {r["doc_id"]: r["base_p"].split(",") for r in secrets.find_secrets(frame(spark, rows)).collect()}
    assert float(got[0][0]) < 1e-3 < float(got[0][1]) and got[1] == ["-"] and got[2] == [""]


def test_battery_levels():
    rng = random.Random(1)
    p = [secrets.battery("".join(rng.choice("0123456789abcdef") for _ in range(64)), "hex") for _ in range(400)]
    assert np.mean(np.array(p) < 0.05) < 0.12
    assert secrets.battery("0123456789abcdef" * 4, "hex") < 1e-3 and secrets.battery("a" * 40, "hex") < 1e-9


# 8 ---------------------------------------------------------------------------------------------------------------------


def test_top_k(spark):
    rng = random.Random(2)
    v = [(i, [rng.gauss(0, 1) for _ in range(6)], "x") for i in range(400)]
    v += [(400, None, "x"), (401, [1.0, None, 0.0, 0.0, 0.0, 0.0], "x"), (402, [math.nan] * 6, "x"), (403, [math.inf] * 6, "x"), (404, v[3][1], "x"), (405, [0.5, 0.25], "x"), (None, [1.0] * 6, "x")]
    df = spark.createDataFrame(v, "vec_id long, embedding array<double>, score string")
    got = [tuple(r) for r in topk.top_k(df, df.filter("vec_id % 50 = 0"), 5, block=16, cell_rows=100, cell_queries=3).orderBy("query_id", "rank").collect()]
    ints = {i: [math.floor(256 * x) for x in e] + [0] * (6 - len(e)) for i, e, _ in v if i is not None and e is not None and all(x is not None and math.isfinite(x) for x in e)}
    want = []
    for q in sorted(i for i in ints if i % 50 == 0):
        best = sorted((-sum(a * b for a, b in zip(ints[q], ints[c])), c) for c in ints if c != q)[:5]
        want += [(q, r + 1, c, -s) for r, (s, c) in enumerate(best)]
    assert got == want
    few = df.filter("vec_id < 3")
    assert topk.top_k(few, few.filter("vec_id = 0")).count() == 2
    assert topk.top_k(df.filter("false"), df.filter("false")).count() == 0


def test_top_k_prunes_blocks():
    rng = np.random.default_rng(0)
    rows = np.round(np.repeat(rng.normal(size=(40, 8)) * 300, 50, axis=0) + rng.normal(size=(2000, 8)) * 5)
    _, _, s, scored = topk.best_of_blocks(rows[:4], np.arange(4), rows, np.arange(2000), 50, 5)
    assert scored < 4 * 40 / 2
    big = np.array([[2.0**40, 1], [2.0**40, 3], [1, 1]])
    assert topk.best_of_blocks(big[:1], np.array([0]), big, np.arange(3), 2, 2)[2].tolist() == [2**80 + 3, 2**40 + 1]


# 1 ---------------------------------------------------------------------------------------------------------------------


def overlap_brute(rows, items):
    tok = lambda t: re.findall(r"[^\W_]+", (t or "").lower())
    out = set()
    for i, t in rows:
        d = tok(t)
        for k, p in items:
            q = tok(p)
            if not q or i is None:
                continue
            w = min(16, len(q))
            need = w if w < 5 else math.ceil(0.8 * w)
            for s in range(-len(q) + 1, len(d)):
                same = [0 <= s + x < len(d) and d[s + x] == q[x] for x in range(len(q))]
                if max(sum(same[a : a + w]) for a in range(len(q) - w + 1)) >= need:
                    out.add((i, k))
    return out


@pytest.mark.parametrize("most", [1_000_000, 0])
def test_decontamination(spark, most):
    rng = random.Random(8)
    items = [(k, prose(rng, n)) for k, n in enumerate((16, 30, 45, 20, 9, 3))] + [(20, None), (21, ""), (22, "...")]
    rows = [(i, prose(rng, 80)) for i in range(10)] + [(90, None), (91, ""), (92, "x" * 3000)]
    for k, p in items[:6]:
        w = p.split()
        rows.append((100 + k, prose(rng, 30) + " " + p.upper() + " " + prose(rng, 10)))
        v = list(w)
        for at in range(3, len(v), 8):
            v[at] = "changed"
        rows.append((200 + k, prose(rng, 5) + " " + "*** ".join(v) + " " + prose(rng, 30)))
        rows.append((300 + k, " ".join(w[: len(w) // 2])))
    rows += rows[10:14]
    b = spark.createDataFrame([(k, p, "clash") for k, p in items], "item_id long, text string, seed string")
    got = {(r["doc_id"], r["item_id"]) for r in decontaminate.contaminated(frame(spark, rows), b, most).collect()}
    assert got == overlap_brute(rows, items)
    assert {(100 + k, k) for k in range(6)} <= got and {(200 + k, k) for k in range(5)} <= got
    assert decontaminate.contaminated(frame(spark, rows), b.filter("false"), most).count() == 0


@pytest.mark.parametrize("most", [1_000_000, 0])
def test_decontamination_of_short_items_and_of_ids_that_repeat(spark, most):
    rng = random.Random(18)
    items = [(n, prose(rng, n)) for n in (5, 6, 7, 8)]
    rows, at = [], 0
    for n, p in items:  # every single change of every item
        for k in range(n):
            v = p.split()
            v[k] = "changed"
            rows.append((at, prose(rng, 6) + " " + " ".join(v) + " " + prose(rng, 6)))
            at += 1
    whole = prose(rng, 16).split()
    rows += [(900, " ".join(whole[:8])), (900, " ".join(whole[8:]))]  # two texts of one id, each with half of an item
    halves = [(50, " ".join(whole)), (60, " ".join(whole[:8] + ["other"] * 8)), (60, " ".join(["else"] * 8 + whole[8:]))]
    rows.append((901, " ".join(whole[:8] + ["third"] + whole[8:])))
    b = spark.createDataFrame(items + halves, "item_id long, text string")
    got = {(r["doc_id"], r["item_id"]): r["matched"] for r in decontaminate.contaminated(frame(spark, rows), b, most).collect()}
    assert set(got) == overlap_brute(rows, items + halves) and len(got) == 26
    assert all(got[i, n] == n - 1 for i, n in got)


# 10 --------------------------------------------------------------------------------------------------------------------


def test_kneser_ney_adds_up_to_one(spark):
    rng = random.Random(3)
    words = frame(spark, [(i, prose(rng, 40)) for i in range(20)])
    model = kneser_ney.kneser_ney(kneser_ney.gram_counts(words)).collect()
    share, left = ({(r["m"], r["hi"], r["lo"]): r[k] for r in model if r[k] is not None} for k in ("a", "g"))
    for m in range(1, 6):  # what a context gives to the symbols after it, and to shorter contexts
        total = Counter()
        for (length, hi, lo), a in share.items():
            if length == m:
                h, w = kneser_ney.context(np.array([hi]), np.array([lo]), m)
                total[m - 1, int(h[0]), int(w[0])] += a
        assert total and all(v + left[k] == pytest.approx(1) for k, v in total.items())


def test_gram_chain_and_packing(monkeypatch):
    monkeypatch.setattr(kneser_ney, "WINDOW", 3)  # windows that end within a text
    texts = pa.array(["abcab", "", None, "c" * 7, "".join(chr(0x4E00 + k) for k in range(9))])
    found = [(hi[i], lo[i], t) for hi, lo, at, text in kneser_ney.windows(texts) for i, t in zip(at.tolist(), text.tolist())]
    spell = lambda hi, lo: "".join(chr(x) for x in (hi >> 42, hi >> 21 & kneser_ney.LOW, hi & kneser_ney.LOW, lo >> 21, lo & kneser_ney.LOW))
    pad = chr(kneser_ney.START) * 4
    assert [(spell(h, w), t) for h, w, t in found] == [((pad + x)[i : i + 5], t) for t, x in enumerate(texts.to_pylist()) for i in range(len(x or ""))]
    hi, lo, _ = kneser_ney.distinct(*(np.array([f[k] for f in found]) for k in (0, 1)))
    levels = kneser_ney.chain(hi, lo)
    grams = {spell(h, w) for h, w in zip(hi.tolist(), lo.tolist())}
    for k, m in enumerate(range(5, 0, -1)):
        longer, shorter = levels[k], levels[k + 1]
        s, c = kneser_ney.suffix(longer[0], longer[1], m), kneser_ney.context(longer[0], longer[1], m)
        assert (shorter[0][longer[2]] == s[0]).all() and (shorter[1][longer[3]] == c[1]).all()
        grams = {g[1:] for g in grams} | {g[:-1] for g in grams}
        assert len(shorter[0]) == len(grams)
    counts, h, w, n = kneser_ney.unpack_grams(kneser_ney.pack_grams(np.array([len(hi)]), hi, lo, np.arange(len(hi))), 1, 1)
    assert counts.tolist() == [len(hi)] and (h == hi).all() and (w == lo).all() and (n == np.arange(len(hi))).all()


def test_classifier_on_held_out_documents(spark, empty):
    rng = random.Random(7)
    stock = prose(rng, 400).split()
    rows = []
    for i in range(240):
        good = i % 4 > 0
        rows.append((i, prose(rng, 60, stock) if good else "".join(rng.choice("zqxjkvw#$! ") for _ in range(300))))
    docs = frame(spark, [*rows, (900, None), (901, "")])
    labels = spark.createDataFrame([(i, int(i % 4 > 0), 0) for i in range(120)], "doc_id long, quality int, toxic int")
    got = {r["doc_id"]: r["keep"] for r in quality.classify(docs, labels, least=20).collect()}
    held = [i for i in range(120, 240)]
    assert sum(got[i] for i in held if i % 4 > 0) >= 0.97 * 90 and not any(got[i] for i in held if i % 4 == 0)
    assert not got[900] and not got[901]
    assert quality.classify(empty, labels).count() == 0
    assert quality.classify(docs, labels.filter("false")).filter("keep").count() >= 240


def test_open_model_tells_scripts_apart_and_matches_brute_force(spark):
    rng = random.Random(12)
    greek = ["".join(rng.choice(["και", "το", "λόγ", "ος", "την", "αν"]) for _ in range(rng.randint(1, 3))) for _ in range(80)]
    rows = [(i, prose(rng, 60, greek)) for i in range(120)] + [(i, "".join(chr(rng.randint(0x370, 0x3FF)) if rng.random() < 0.8 else " " for _ in range(300))) for i in range(120, 160)]
    rows += [(200, "".join(chr(0x4E00 + k) for k in range(9000))), (201, None), (202, "")]  # an alphabet too wide for packed codes
    labels = spark.createDataFrame([(i, 1, 0) for i in range(60)], "doc_id long, quality int, toxic int")
    got = {r["doc_id"]: r for r in quality.classify(frame(spark, rows), labels, least=20).collect()}
    assert sum(got[i]["keep"] for i in range(60, 120)) >= 57 and not any(got[i]["keep"] for i in [*range(120, 160), 200, 201, 202])
    # brute force over the same counts
    k, start = kneser_ney.ORDER, chr(kneser_ney.START)
    texts = dict(rows)
    seen = Counter(g for i in range(60) for t in [start * (k - 1) + texts[i]] for g in (t[j : j + k] for j in range(len(texts[i]))))
    levels = {k: seen}
    for m in range(k - 1, 0, -1):
        levels[m] = Counter(g[1:] for g in levels[m + 1])
    cut, total, kinds = {}, {}, {}
    for m, c in levels.items():
        t1, t2, t3, t4 = (sum(v == x for v in c.values()) for x in (1, 2, 3, 4))
        y = t1 / (t1 + 2 * t2) if t1 and t2 else 0.5
        cut[m] = [min(max(d, 0.05), cap) for d, cap in ((1 - 2 * y * t2 / t1 if t1 else 0.5, 0.95), (2 - 3 * y * t3 / t2 if t2 else 1.0, 1.9), (3 - 4 * y * t4 / t3 if t3 else 1.5, 2.9))]
        total[m], kinds[m] = Counter(), defaultdict(float)
        for g, v in c.items():
            total[m][g[:-1]] += v
            kinds[m][g[:-1]] += cut[m][min(v, 3) - 1]

    def p(g):
        m = len(g)
        if not m:
            return 1 / kneser_ney.POINTS
        n, all_ = levels[m][g], total[m][g[:-1]]
        return p(g[1:]) if not all_ else ((n - cut[m][min(n, 3) - 1]) if n else 0) / all_ + kinds[m][g[:-1]] / all_ * p(g[1:])

    for i in (70, 130, 200):
        t = start * (k - 1) + texts[i]
        want = math.exp(-sum(math.log(p(t[j : j + k])) for j in range(len(texts[i]))) / len(texts[i]))
        assert got[i]["perplexity"] == pytest.approx(want, rel=1e-4, abs=2e-3)


def test_classifier_catches_toxic_words_and_heeds_length(spark):
    rng = random.Random(13)
    stock = prose(rng, 60).split()
    mark = lambda t, w: " ".join([*t.split()[:30], w, *t.split()[30:]])
    rows = [(i, prose(rng, 150, stock)) for i in range(150)] + [(i, mark(prose(rng, 150, stock), rng.choice(["trash", "scum"]))) for i in range(150, 190)]
    rows += [(i, "Zq " + chr(97 + i % 26) + "xj.") for i in range(200, 260)]  # trusted fragments that are hard to predict
    junk = [(i, " ".join(w[::-1] if k % 2 else w for k, w in enumerate(prose(rng, 150, stock).split()))) for i in range(300, 320)]
    labels = spark.createDataFrame([(i, 1, int(150 <= i < 190)) for i in [*range(100), *range(150, 170), *range(200, 260)]], "doc_id long, quality int, toxic int")
    docs = spark.createDataFrame([(i, t, "en") for i, t in rows + junk], "doc_id long, text string, lang string")
    keep = {r["doc_id"]: r["keep"] for r in quality.classify(docs, labels).collect()}
    assert sum(keep[i] for i in range(100, 150)) >= 48
    assert not any(keep[i] for i in range(150, 190)) and not any(keep[i] for i in range(300, 320))


# the pipeline ------------------------------------------------------------------------------------------------------------


def test_pipeline_stages(spark, tmp_path):
    rng = random.Random(11)
    item = prose(rng, 30)
    good = [(i, prose(rng, 80)) for i in range(30)]
    rows = good + [(40, good[0][1]), (41, good[1][1] + " more"), (42, prose(rng, 30) + " " + item), (43, "#$!" * 200), (44, f"{prose(rng, 400)} mail a.b@c.de now and {prose(rng, 200)}"), (45, None)]
    frame(spark, rows).write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(i, 1, 0) for i in range(25)], "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    spark.createDataFrame([(0, item)], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    docs, kept = spark.read.parquet(f"{tmp_path}/documents.parquet"), {}
    for k, (name, stage) in enumerate(corpus_pipeline.STAGES):
        stage(spark, docs, str(tmp_path)).write.parquet(f"{tmp_path}/{k}")
        docs = spark.read.parquet(f"{tmp_path}/{k}")
        kept[k] = {r["doc_id"] for r in docs.select("doc_id").collect()}
        if k < 4:
            assert set(docs.columns) == set(corpus_pipeline.COLUMNS)
    assert 43 not in kept[0] and 45 not in kept[0] and set(range(25)) <= kept[0]
    assert kept[1] == kept[0] - {40, 41}
    assert kept[2] == kept[1] - {42}
    assert kept[3] == kept[2] == kept[4]
    text = spark.read.parquet(f"{tmp_path}/3").filter("doc_id = 44").first()
    assert "<email>" in text["text"] and "a.b@c.de" not in text["text"] and text["n_chars"] == len(text["text"])
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == len(kept[4])


def test_redaction_of_spans_that_overlap():
    assert pii.without_spans("ab 12 cd 34 ef", "ip:3:5,card:4:9,phone:12:14") == "ab <ip>34 <phone>"
    assert pii.without_spans("x" * 3, "email:0:3") == "<email>"


def test_pipeline_of_rows_without_ids_repeated_ids_and_no_rows(spark, tmp_path):
    rng = random.Random(12)
    stock = prose(rng, 300).split()
    item = prose(rng, 30, stock)
    good = [(i, prose(rng, 120, stock)) for i in range(60)]
    mail = f"{prose(rng, 90, stock)} mail a.b@c.de now and {prose(rng, 40, stock)}"
    odd = [(None, prose(rng, 120, stock)), (None, prose(rng, 120, stock)), (None, mail), (None, prose(rng, 100, stock) + " " + item), (70, prose(rng, 120, stock)), (70, prose(rng, 120, stock)), (70, mail + " so"), (71, good[3][1]), (71, good[3][1]), (None, good[4][1])]
    rows = [*good, *odd, (72, odd[4][1]), (73, "w " * 50000)]
    frame(spark, rows).withColumn("key", F.lit("clash")).withColumn("spans", F.lit("clash")).write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(i, 1, 0) for i in range(60)], "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    spark.createDataFrame([(0, item)], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    docs = spark.read.parquet(f"{tmp_path}/documents.parquet")
    of = lambda df: Counter((r["doc_id"], r["text"]) for r in df.collect())
    kept = of(corpus_pipeline.near_duplicates(spark, docs, str(tmp_path)))
    assert max(kept.values()) == 1 and set(kept) == set(rows) - {(71, good[3][1]), (None, good[4][1]), (72, odd[4][1]), (70, mail + " so"), (None, mail)} | ({(70, mail + " so")})
    clean = of(corpus_pipeline.decontamination(spark, docs, str(tmp_path)))
    assert clean == Counter(rows) - Counter([odd[3]])
    safe = corpus_pipeline.private_data(spark, docs, str(tmp_path)).collect()
    assert len(safe) == len(rows) and sum("<email>" in r["text"] for r in safe) == 2 and not any("a.b@c.de" in r["text"] or r["n_chars"] != len(r["text"]) for r in safe)
    good_only = of(corpus_pipeline.quality(spark, docs, str(tmp_path)))
    assert not any(i == 73 for i, _ in good_only) and good_only[odd[0]] == 1 and good_only[71, good[3][1]] == 2 and good_only[odd[4]] == 1
    for _, stage in corpus_pipeline.STAGES:
        assert stage(spark, docs.filter("false"), str(tmp_path)).count() == 0
