"""The queries of the training-data operators: each applies one operator to its whole table."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from rowfold.llm import pieces
from rowfold.llm.common import table
from rowfold.llm.decontaminate import MASKS, contaminated
from rowfold.llm.jaccard import jaccard_groups
from rowfold.llm.pii import find_pii
from rowfold.llm.quality import classify
from rowfold.llm.secrets import find_secrets
from rowfold.llm.sharding import shard_by_bytes
from rowfold.llm.substring_dedup import remove_repeats
from rowfold.llm.token_counts import tokens_by_document
from rowfold.llm.topk import top_k

PIECE_MODEL = "/opt/tokenizers/piece_bpe_32k.model"


def op1_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents that overlap a benchmark item, with each item and its best window."""
    return contaminated(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op2_byte_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents into shards 0 to 7, contiguous by doc_id and near equal in bytes."""
    return shard_by_bytes(table(spark, sf_dir, "documents"), 8)


def op3_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What is left of every document without byte strings of earlier ones."""
    return remove_repeats(table(spark, sf_dir, "documents"))


def op4_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Personal data of every document."""
    return find_pii(table(spark, sf_dir, "documents"))


def op5_sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Piece ids of every document, decoded again and compared."""
    return pieces.encode(table(spark, sf_dir, "documents"), PIECE_MODEL)


def op6_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Shingle-set sizes and near-duplicate components of all documents."""
    return jaccard_groups(table(spark, sf_dir, "documents"))


def op7_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Secrets of every document."""
    return find_secrets(table(spark, sf_dir, "documents"))


def op8_exact_top_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The five best inner products of every fiftieth vector against all others."""
    v = table(spark, sf_dir, "embeddings").select("vec_id", "embedding")
    return top_k(v, v.filter("vec_id % 50 = 0"))


def op9_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Tokens of every document, counted from flat token streams."""
    return tokens_by_document(table(spark, sf_dir, "documents"), PIECE_MODEL)


def op10_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Perplexity of every document under the model of trusted text, and whether it is kept."""
    return classify(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f
    for f in (op1_decontamination, op2_byte_shards, op3_suffix_dedup, op4_pii, op5_sentencepiece, op6_jaccard_join, op7_secret_scan, op8_exact_top_k, op9_token_counts, op10_quality)
}

_MASKED = " union all ".join(
    f"select id, pos, concat_ws('|', {k}, " + ", ".join(f"toks[pos + {i + 1}]" for i, c in enumerate(m) if c == "1") + f") as seed from {{t}}p where pos + {len(m)} <= len(toks)" for k, m in enumerate(MASKS)
)
_TOKENS = "list_filter(string_split_regex(trim(regexp_replace(lower(coalesce(text, '')), '[^\\p{L}\\p{N}]+', ' ', 'g')), ' '), lambda w: w <> '')"
_WORDS = "list_filter(string_split_regex(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\\x20\\x09-\\x0D]+'), lambda w: w <> '')"

ORACLE: dict[str, str] = {
    "op1_decontamination": f"""
        with d as materialized (select doc_id as id, {_TOKENS} as toks from documents), b as materialized (select item_id as id, {_TOKENS} as toks from benchmark),
        dp as (select id, toks, unnest(range(len(toks))) as pos from d), bp as (select id, toks, unnest(range(len(toks))) as pos from b),
        ds as ({_MASKED.format(t='d')}), bs as materialized ({_MASKED.format(t='b')}),
        a as materialized (select distinct ds.id as doc_id, bs.id as item_id, ds.pos - bs.pos as shift from ds join bs using (seed)),
        e as (select doc_id, item_id, shift, b.toks as item, d.toks as toks, unnest(range(len(b.toks))) as i from a join d on d.id = doc_id join b on b.id = item_id),
        m as (select doc_id, item_id, shift, len(item) as n, i from e where shift + i >= 0 and shift + i < len(toks) and toks[shift + i + 1] = item[i + 1]),
        w as (select x.doc_id, x.item_id, least(16, x.n) as width, x.i, count(*) as hit from m x join m y on x.doc_id = y.doc_id and x.item_id = y.item_id and x.shift = y.shift and y.i >= x.i and y.i < x.i + least(16, x.n) group by x.doc_id, x.item_id, x.shift, x.n, x.i)
        select doc_id, item_id, max(hit)::bigint as matched, max(width)::bigint as width from w where hit >= ceil(0.8 * width) group by 1, 2""",
    "op2_byte_shards": """
        with tab as (select list(c order by i) as t from (select i, list_reduce(list_prepend(i, range(8)), lambda c, k: case when c & 1 = 1 then xor(c >> 1, 3988292384) else c >> 1 end) as c from range(256) r(i))),
        d as (select doc_id, hex(encode(coalesce(text, ''))) as h, octet_length(encode(coalesce(text, ''))) as n from documents),
        c as (select doc_id, n, xor(list_reduce(list_prepend(4294967295::bigint, list_transform(range(n), lambda i: ('0x' || substr(h, 2 * i + 1, 2))::bigint)), lambda a, b: xor(a >> 8, t[(xor(a, b) & 255) + 1])), 4294967295) as crc from d, tab),
        s as (select doc_id, n + 1 as size, crc, sum(n + 1) over (order by doc_id nulls first, n, crc rows between unbounded preceding and current row) - n - 1 as before, sum(n + 1) over () as total from c),
        p as (select *, (before * 8 // total)::int as shard from s)
        select doc_id, size::bigint as size, crc::bigint as text_crc32, 'bytes' as law, shard, row_number() over (partition by shard order by before) - 1 as slot, null::int as grown_shard, before::bigint as global_offset from p""",
    "op6_jaccard_join": f"""
        with recursive d as materialized (select doc_id, {_WORDS} as w from documents),
        s as materialized (select distinct doc_id, unnest(case when len(w) >= 5 then list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i + 4], ' ')) when len(w) > 0 then [array_to_string(w, ' ')] else [] end) as g from d),
        n as materialized (select doc_id, count(*) as n from s group by 1),
        p as (select a.doc_id as a, b.doc_id as b, count(*) as c from s a join s b on a.g = b.g and a.doc_id <> b.doc_id group by 1, 2),
        l as materialized (select a, b from p join n x on x.doc_id = a join n y on y.doc_id = b where 100 * c >= 80 * (x.n + y.n - c)),
        r(a, b) as (select doc_id, doc_id from d union select r.a, l.b from r join l on l.a = r.b)
        select d.doc_id, coalesce(n.n, 0) as n_shingles, min(r.b) as component_id from d join r on r.a = d.doc_id left join n on n.doc_id = d.doc_id group by 1, 2""",
    "op8_exact_top_k": """
        with v as (
          select vec_id, list_transform(embedding, lambda x: cast(floor(256 * cast(x as double)) as bigint)) as q
          from embeddings
          where vec_id is not null and embedding is not null
            and len(list_filter(embedding, lambda x: x is null or not isfinite(x))) = 0
        ), s as (
          select a.vec_id as query_id, b.vec_id,
            cast(list_sum(list_transform(list_zip(a.q, b.q), lambda p: p[1] * p[2])) as bigint) as score
          from v a join v b on a.vec_id <> b.vec_id where a.vec_id % 50 = 0
        )
        select query_id, cast(row_number() over (partition by query_id order by score desc, vec_id) as int) as rank, vec_id, score
        from s qualify rank <= 5""",
}
