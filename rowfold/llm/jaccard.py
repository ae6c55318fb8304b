"""Exact Jaccard join on word shingles by token-combination prefixes.

Tokens are shingle hashes. Texts with equal sets become one node first, so copies
cost nothing further. One shuffle counts every token; tokens of a single node can
link nothing and are only counted, which leaves each node its shared tokens,
rarest first. Two sets that reach the threshold share their first common token
within short prefixes of that order, the smaller set within a shorter one. Rare
tokens index their nodes alone; where the first common token is frequent, so are
all, and prefixes extended by one place share a pair of them, so frequent tokens
are indexed by pairs. Nodes first link to a pivot of each index entry, which joins
most of a group of near copies by one comparison each; only pairs that lie in
different components after that are compared, behind filters on size, place and
the parity bits of both sets that never lose a link.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rowfold.llm.common import parts_for, release, slices, staged, text_bytes, utf8
from rowfold.llm.components import components
from rowfold.llm.shingles import U, mix, set_keys, shingle_sets

BATCH = 1 << 20
FREQUENT = 512  # nodes that hold a token before it counts as frequent
WIDE = 24  # frequent tokens of a prefix beyond which a node is indexed by them singly
GROUP = 512  # index entries of one key on one side of a comparison cell
BITS = 1024
MANY = 1000  # sets of a component that counts as large, or a millionth of all sets where that is more


def _sets(docs: DataFrame, id_col: str, text_col: str, k: int) -> DataFrame:
    """(id, n_shingles, node): node is the set's key, null for an empty set."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches, 1, BATCH):
            g, n = shingle_sets(*utf8(b.column(1)), k)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(n), pa.array(set_keys(g, n).view(np.int64), mask=n == 0)], names=[id_col, "n_shingles", "node"])

    src = docs.select(id_col, text_col)
    return src.mapInArrow(work, f"{id_col} {dict(src.dtypes)[id_col]}, n_shingles long, node long")


def _pack(*arrays: np.ndarray) -> bytes:
    return b"".join(np.ascontiguousarray(a).tobytes() for a in arrays)


def _dealt(key: np.ndarray, parts: int) -> tuple[np.ndarray, np.ndarray]:
    """The order that sorts by part (the high bits of the mixed key), and where each part begins."""
    part = (mix(key) >> U(32)) * U(parts) >> U(32)
    order = np.argsort(part, kind="stable")
    return order, np.searchsorted(part[order], np.arange(parts + 1))


def _token_blocks(docs: DataFrame, text_col: str, k: int, parts: int) -> DataFrame:
    """(part, data): per batch and part of the token space, the nodes with tokens there. Equal sets of a batch go
    once. data: number of nodes m, their keys, sizes and counts here, then the tokens node by node."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches, 0, BATCH):
            g, n = shingle_sets(*utf8(b.column(0)), k)
            key = set_keys(g, n)
            _, first = np.unique(key, return_index=True)
            kept = np.zeros(len(key), bool)
            kept[first] = True
            kept &= n > 0
            doc = np.repeat(np.arange(len(n)), n)
            doc, g = doc[kept[doc]], g[kept[doc]]
            order, at = _dealt(g, parts)
            doc, g = doc[order], g[order]  # stable: within a part still by node
            part, data = [], []
            for p in range(parts):
                a, z = at[p], at[p + 1]
                if a < z:
                    own, counts = np.unique(doc[a:z], return_counts=True)
                    part.append(p)
                    data.append(_pack(np.array([len(own)], np.int64), key[own], n[own].astype(np.int32), counts.astype(np.int32), g[a:z]))
            yield pa.RecordBatch.from_arrays([pa.array(part, pa.int32()), pa.array(data, pa.binary())], names=["part", "data"])

    return docs.select(text_col).mapInArrow(work, "part int, data binary")


def _groups(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, list[pa.RecordBatch]]]:
    """Rows of each value of the first column, which is sorted, one value at a time."""
    held: list[pa.RecordBatch] = []
    now = None
    for b in batches:
        key = np.asarray(b.column(0))
        cuts = np.flatnonzero(np.diff(key)) + 1
        for a, z in zip([0, *cuts], [*cuts, len(key)]):
            if a == z:
                continue
            if now is not None and key[a] != now:
                yield int(now), held
                held = []
            now = key[a]
            held.append(b.slice(a, z - a))
    if held:
        yield int(now), held


def _shared_tokens(blocks: DataFrame, parts: int) -> DataFrame:
    """(part, data) by part of the node space, of tokens that two or more nodes hold.
    data: number of tokens m, then the nodes, tokens, sizes of the nodes and numbers of nodes that hold each token."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _, rows in _groups(batches):
            node, size, token = [], [], []
            for b in rows:
                for x in b.column(1):
                    raw = x.as_buffer()
                    m = int(np.frombuffer(raw, np.int64, 1)[0])
                    count = np.frombuffer(raw, np.int32, m, 8 + 12 * m)
                    node.append(np.repeat(np.frombuffer(raw, U, m, 8), count))
                    size.append(np.repeat(np.frombuffer(raw, np.int32, m, 8 + 8 * m), count))
                    token.append(np.frombuffer(raw, U, -1, 8 + 16 * m))
            node, size, token = np.concatenate(node), np.concatenate(size), np.concatenate(token)
            order = np.argsort(token, kind="stable")
            node, size, token = node[order], size[order], token[order]
            more = np.zeros(len(token), bool)
            more[1:] = token[1:] == token[:-1]
            more[:-1] |= more[1:]
            node, size, token = node[more], size[more], token[more]
            order = np.lexsort((node, token))  # equal sets of several batches
            node, size, token = node[order], size[order], token[order]
            new = np.ones(len(token), bool)
            new[1:] = (token[1:] != token[:-1]) | (node[1:] != node[:-1])
            node, size, token = node[new], size[new], token[new]
            if not len(token):
                continue
            start = np.flatnonzero(np.concatenate([[True], token[1:] != token[:-1]]))
            df = np.diff(np.append(start, len(token)))
            keep = np.repeat(df, df) > 1
            df = np.repeat(df, df)[keep].astype(np.int32)
            node, size, token = node[keep], size[keep], token[keep]
            order, at = _dealt(node, parts)
            part = np.flatnonzero(np.diff(at))
            data = []
            for p in part:
                o = order[at[p] : at[p + 1]]
                data.append(_pack(np.array([len(o)], np.int64), node[o], token[o], size[o], df[o]))
            yield pa.RecordBatch.from_arrays([pa.array(part, pa.int32()), pa.array(data, pa.binary())], names=["part", "data"])

    return blocks.mapInArrow(work, "part int, data binary")


def overlap_needed(a, b, pct: int):
    """Least intersection with which sets of sizes a and b reach pct per cent: 100 i >= pct (a + b - i)."""
    return -(-pct * (a + b) // (100 + pct))


def _nodes(shared: DataFrame, pct: int) -> DataFrame:
    """(node, n, alone, rare, tokens, bits) of the nodes that can link. alone: tokens no other node holds; tokens: the
    others, by rising number of holders; rare: how many of them are not frequent; bits: parity bits of tokens."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _, rows in _groups(batches):
            cols: list[list] = [[], [], [], []]
            for b in rows:
                for x in b.column(1):
                    raw = x.as_buffer()
                    m = int(np.frombuffer(raw, np.int64, 1)[0])
                    for c, (kind, at) in zip(cols, ((U, 8), (U, 8 + 8 * m), (np.int32, 8 + 16 * m), (np.int32, 8 + 20 * m))):
                        c.append(np.frombuffer(raw, kind, m, at))
            node, token, size, df = (np.concatenate(c) for c in cols)
            order = np.lexsort((token, df, node))
            node, token, size, df = node[order], token[order], size[order], df[order]
            start = np.flatnonzero(np.concatenate([[True], node[1:] != node[:-1]]))
            count = np.diff(np.append(start, len(node)))
            n = size[start].astype(np.int64)
            can = 100 * count >= pct * n  # the shared tokens alone could reach the threshold
            rare = np.add.reduceat((df < FREQUENT).astype(np.int64), start)
            bit = (mix(token) % U(BITS)).astype(np.int64)
            bits = np.zeros((len(start), BITS), np.uint8)
            np.add.at(bits, (np.repeat(np.arange(len(start)), count), bit), 1)
            packed = np.packbits(bits & 1, axis=1)
            which = np.flatnonzero(can)
            kept = token[np.repeat(can, count)]
            upto = np.concatenate([[0], np.cumsum(count[which])])
            for i in range(0, len(which), 2000):
                w = which[i : i + 2000]
                off = upto[i : i + len(w) + 1]
                own = kept[off[0] : off[-1]]
                yield pa.RecordBatch.from_arrays(
                    [pa.array(node[start[w]].view(np.int64)), pa.array(n[w]), pa.array(n[w] - count[w]), pa.array(rare[w]), pa.LargeListArray.from_arrays(pa.array(off - off[0]), pa.array(own.view(np.int64))).cast(pa.list_(pa.int64())), pa.array([x.tobytes() for x in packed[w]], pa.binary())],
                    names=["node", "n", "alone", "rare", "tokens", "bits"],
                )

    return shared.mapInArrow(work, "node long, n long, alone long, rare long, tokens array<long>, bits binary")


def index_entries(n: int, alone: int, rare: int, tokens: np.ndarray, pct: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(keys, places, roles) under which a node is indexed. place: of the (first) token in the whole order. role bits:
    1 if the place is in the prefix of a smaller set, 2 in that of a larger one, 4 if the entry is a single frequent
    token (compared only where one side is wide), 8 if the node is wide."""
    small = n - overlap_needed(n, n, pct) + 1  # the other set is no smaller
    large = n - -(-pct * n // 100) + 1  # the other set is no larger
    place = alone + np.arange(len(tokens))
    single = tokens[: max(0, min(len(tokens), large - alone))]
    at = place[: len(single)]
    role = 2 + (at < small).astype(np.int64)
    often = np.arange(len(single)) >= rare
    keys, places, roles = [single], [at], [role + 4 * often]
    last = min(len(tokens), large + 1 - alone)
    m = last - rare
    if m > WIDE:
        roles[0] = roles[0] + 8 * often
    elif m > 1:
        i, j = np.triu_indices(m, 1)
        i, j = i + rare, j + rare
        keys.append(mix(tokens[i] * U(0x9E3779B97F4A7C15) + tokens[j]))
        places.append(place[i])
        roles.append(2 * (place[i] < large) + ((place[j] < small + 1) & (place[i] < small)).astype(np.int64))
    return np.concatenate(keys), np.concatenate(places), np.concatenate(roles)


def _postings(nodes: DataFrame, pct: int) -> DataFrame:
    """(key, node, n, alone, place, role): the inverted index."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            node, n, alone, rare = (np.asarray(b.column(i)) for i in range(4))
            off, flat = np.asarray(b.column(4).offsets), np.asarray(b.column(4).values).view(U)
            key, place, role, size = [], [], [], []
            for i in range(len(node)):
                k, p, r = index_entries(int(n[i]), int(alone[i]), int(rare[i]), flat[off[i] : off[i + 1]], pct)
                key.append(k), place.append(p), role.append(r), size.append(len(k))
            yield pa.RecordBatch.from_arrays(
                [pa.array(np.concatenate(key).view(np.int64)), pa.array(np.repeat(node, size)), pa.array(np.repeat(n, size)), pa.array(np.repeat(alone, size)), pa.array(np.concatenate(place)), pa.array(np.concatenate(role))],
                names=["key", "node", "n", "alone", "place", "role"],
            )

    return nodes.select("node", "n", "alone", "rare", "tokens").mapInArrow(work, "key long, node long, n long, alone long, place long, role long")


def verified(pairs: DataFrame, nodes: DataFrame, pct: int) -> DataFrame:
    """The pairs (a, b) of nodes whose sets reach the threshold."""
    x = nodes.select(F.col("node").alias("a"), F.col("n").alias("na"), F.col("tokens").alias("ta"))
    y = nodes.select(F.col("node").alias("b"), F.col("n").alias("nb"), F.col("tokens").alias("tb"))
    both = F.size(F.array_intersect("ta", "tb"))
    return pairs.join(x, "a").join(y, "b").filter(100 * both >= pct * (F.col("na") + F.col("nb") - both)).select("a", "b")


def _pairs_of(left: np.ndarray, right: np.ndarray, key: np.ndarray, node: np.ndarray, n: np.ndarray, alone: np.ndarray, place: np.ndarray, role: np.ndarray, comp: np.ndarray, bits: np.ndarray, pct: int) -> tuple[np.ndarray, np.ndarray]:
    """Pairs of rows of one index entry, one from each side, in different components, that pass all filters. Where both
    sides are the same rows, each pair is taken once."""
    out_a, out_b = [], []
    once = len(left) == len(right) and (left == right).all()
    for at in range(0, len(left), 64):
        r = left[at : at + 64]
        other = comp[r][:, None] != comp[right][None, :]
        if once:
            other &= node[r][:, None] < node[right][None, :]
        i, j = np.nonzero(other)
        i, j = r[i], right[j]
        swap = (n[i] > n[j]) | ((n[i] == n[j]) & (node[i] > node[j]))
        s, t = np.where(swap, j, i), np.where(swap, i, j)  # s is the smaller set
        need = overlap_needed(n[s], n[t], pct)
        ok = (n[s] >= need) & (role[t] & 2 > 0)
        ok &= ((role[s] & 4) == 0) | ((role[s] | role[t]) & 8 > 0)
        ok &= 1 + np.minimum(n[s] - 1 - place[s], n[t] - 1 - place[t]) >= need
        equal = n[s] == n[t]  # which of equal sizes is the smaller is open, so both ways must fail to drop a pair
        ok &= (role[s] & 1 > 0) | (equal & (role[t] & 1 > 0))
        s, t, need = s[ok], t[ok], need[ok]
        if len(s):
            apart = np.bitwise_count(bits[s] ^ bits[t]).sum(axis=1, dtype=np.int64) + alone[s] + alone[t]
            near = apart <= n[s] + n[t] - 2 * need
            s, t = s[near], t[near]
            out_a.append(node[s])
            out_b.append(node[t])
    none = np.zeros(0, np.int64)
    return np.concatenate([none, *out_a]), np.concatenate([none, *out_b])


def _close_pairs(entries: DataFrame, pct: int) -> DataFrame:
    """(a, b) from entries (key, i, j, g, node, n, alone, place, role, comp, bits), sorted by key, i and j: a cell (i, j) of
    a key compares its rows of group i with those of group j."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list = []

        def done(rows: list) -> pa.RecordBatch:
            t = pa.Table.from_batches(rows)
            key, i, j, g, *cols = (t.column(k).to_numpy() for k in range(10))
            bits = np.frombuffer(b"".join(t.column(10).to_pylist()), np.uint8).reshape(len(key), BITS // 8)
            cuts = np.flatnonzero((np.diff(key) != 0) | (np.diff(i) != 0) | (np.diff(j) != 0)) + 1
            a, b = [], []
            for u, z in zip([0, *cuts], [*cuts, len(key)]):
                own = [c[u:z] for c in cols]
                x, y = _pairs_of(np.flatnonzero(g[u:z] == i[u]), np.flatnonzero(g[u:z] == j[u]), key[u:z], *own, bits[u:z], pct)
                a.append(x)
                b.append(y)
            a, b = np.concatenate(a), np.concatenate(b)
            both = np.unique(np.stack([np.minimum(a, b), np.maximum(a, b)], axis=1), axis=0)
            return pa.RecordBatch.from_arrays([pa.array(both[:, 0]), pa.array(both[:, 1])], names=["a", "b"])

        for batch in batches:  # whole cells at a time; a cell has at most about 2 GROUP rows
            cell = np.stack([np.asarray(batch.column(k)).astype(np.int64) for k in range(3)])
            cuts = np.flatnonzero((np.diff(cell) != 0).any(axis=0))
            if held and batch.num_rows and [held[-1].column(k)[-1].as_py() for k in range(3)] != cell[:, 0].tolist():
                yield done(held)
                held = []
            if len(cuts):
                z = int(cuts[-1]) + 1
                yield done([*held, batch.slice(0, z)])
                held, batch = [], batch.slice(z)
            if batch.num_rows:
                held.append(batch)
        if held:
            yield done(held)

    cols = ["key", "i", "j", "g", "node", "n", "alone", "place", "role", "comp", "bits"]
    return entries.select(*cols).mapInArrow(work, "a long, b long")


def _links(nodes: DataFrame, pct: int, parts: int) -> tuple[DataFrame, DataFrame]:
    """All links found by pivots, and the links between their components."""
    entries = staged(_postings(nodes, pct), "jaccard-index")
    fit = lambda a, b: 100 * F.least(a, b) >= pct * F.greatest(a, b)
    # pivots: the node with the fewest tokens of its own
    pivot = entries.groupBy("key").agg(F.min(F.struct((F.col("alone") / F.col("n")).alias("s"), "node", "n")).alias("p"), F.count("*").alias("size")).filter("size > 1")
    pairs = entries.join(pivot.select("key", F.col("p.node").alias("pivot"), F.col("p.n").alias("pn")), "key").filter((F.col("node") != F.col("pivot")) & fit(F.col("n"), F.col("pn")))
    pairs = pairs.select(F.least("node", "pivot").alias("a"), F.greatest("node", "pivot").alias("b")).distinct()
    first = staged(verified(pairs, nodes, pct), "jaccard-pivots")
    del pivot, pairs
    release(nodes.sparkSession)
    comp = staged(components(first), "jaccard-comps")
    placed = entries.join(comp, "node", "left").withColumn("comp", F.coalesce("comp", "node"))
    lists = placed.groupBy("key").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi"), F.min(F.struct((F.col("alone") / F.col("n")).alias("s"), "comp")).alias("p"), F.count("*").alias("size")).filter("lo <> hi").select("key", "size", F.col("p.comp").alias("main"))
    live = placed.join(lists, "key").withColumn("minor", F.col("comp") != F.col("main"))
    # groups of a key: first those of its minor nodes, then those of its main component; a cell pairs a minor group with one
    # that is not before it, so no task holds a key and no pair of the main component is formed
    minors = live.filter("minor").groupBy("key").agg(F.count("*").alias("minors"))
    live = live.join(minors, "key").withColumns({"few": F.ceil(F.col("minors") / GROUP).cast("int"), "many": F.ceil((F.col("size") - F.col("minors")) / GROUP).cast("int")})
    deal = F.xxhash64("node")
    live = live.withColumn("g", F.when(F.col("minor"), F.pmod(deal, F.col("few"))).otherwise(F.col("few") + F.pmod(deal, F.greatest("many", F.lit(1)))).cast("int"))
    before = F.when(F.col("g") > 0, F.transform(F.sequence(F.lit(0), F.least("g", "few") - 1), lambda k: F.struct(k.alias("i"), F.col("g").alias("j"))))
    after = F.when(F.col("minor"), F.transform(F.sequence("g", F.col("few") + F.col("many") - 1), lambda k: F.struct(F.col("g").alias("i"), k.alias("j"))))
    none = F.array().cast("array<struct<i:int,j:int>>")
    live = live.withColumn("cell", F.explode(F.concat(F.coalesce(before, none), F.coalesce(after, none)))).select("key", "cell.i", "cell.j", "g", "node", "n", "alone", "place", "role", "comp")
    live = live.join(nodes.select("node", "bits"), "node").repartition(parts, "key", "i", "j").sortWithinPartitions("key", "i", "j")
    second = verified(staged(_close_pairs(live, pct).distinct(), "jaccard-pairs"), nodes, pct)
    return comp, second


def jaccard_groups(docs: DataFrame, pct: int = 80, k: int = 5, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per input row: id, n_shingles, component_id (the least id reachable by links of at least pct per cent).

    Words are runs of anything but ASCII white space, A-Z lower-cased; fewer than k words make one shingle. A text
    that is null or has no words has an empty set and links with nothing, so its component is its own id. Null ids
    take part but name no component unless alone. Repeated rows keep their rows; an empty table gives none; further
    columns are ignored. Sets that share a 64-bit key count as equal.
    """
    total = text_bytes(docs, text_col)
    parts = parts_for(docs, total, 8 << 20)
    sets = staged(_sets(docs, id_col, text_col, k), "jaccard-sets")
    blocks = _token_blocks(docs, text_col, k, parts).repartition(parts, "part").sortWithinPartitions("part")
    shared = _shared_tokens(blocks, parts).repartition(parts, "part").sortWithinPartitions("part")
    nodes = staged(_nodes(shared, pct), "jaccard-nodes")
    del blocks, shared
    release(docs.sparkSession)
    comp, second = _links(nodes, pct, parts)
    named = comp.select(F.col("node"), F.col("comp"))
    between = (
        second.join(named.select(F.col("node").alias("a"), F.col("comp").alias("ca")), "a", "left").join(named.select(F.col("node").alias("b"), F.col("comp").alias("cb")), "b", "left")
        .select(F.coalesce("ca", "a").alias("a"), F.coalesce("cb", "b").alias("b"))
    )
    over = components(between).select(F.col("node").alias("comp"), F.col("comp").alias("top"))
    classes = sets.filter("node is not null").groupBy("node").agg(F.min(id_col).alias("least"))
    top = classes.join(named, "node", "left").withColumn("comp", F.coalesce("comp", "node")).join(over, "comp", "left").withColumn("top", F.coalesce("top", "comp"))
    # large components are few, at most a million, so theirs are broadcast; a shuffle by component would put each into one task
    least = staged(top.groupBy("top").agg(F.min("least").alias("component_id"), F.count("*").alias("size")), "jaccard-least")
    many = max(MANY, (least.agg(F.coalesce(F.sum("size"), F.lit(0))).first()[0]) // 1_000_000)
    placed = top.join(F.broadcast(least.filter(F.col("size") > many).select("top", F.col("component_id").alias("of_large"), F.lit(True).alias("large"))), "top", "left")
    rest = placed.filter("large is null").select("node", "top").join(least.select("top", "component_id"), "top").select("node", "component_id")
    member = rest.unionByName(placed.filter("large").select("node", F.col("of_large").alias("component_id")))
    return sets.join(member, "node", "left").select(id_col, "n_shingles", F.coalesce("component_id", F.col(id_col)).alias("component_id"))
