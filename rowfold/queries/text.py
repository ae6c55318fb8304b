"""Features, chains, grams and text tasks."""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

from rowfold.core.driver import stage
from rowfold.operators import chains as C
from rowfold.operators import evaluate as E
from rowfold.operators import tasks as T
from rowfold.operators import textops as X
from rowfold.queries.base import INSULTS, table

LABELS = 3
#: Integer weights of a toy model (fixed values): by token shape and label, and between labels.
TRANS = np.array([[2, 0, 1], [1, 2, 0], [0, 1, 2]], float)
EMIT = {"lower": (3, 0, 1), "title": (1, 4, 0), "other": (0, 1, 3)}


def _tokens(spark, sf, most=None):
    return X.tokenize(table(spark, sf, "documents"), "doc_id", "text", r"[^ \n\t\r]+", most)


TOK_SQL = "select doc_id, i - 1 as pos, toks[i] as token from (select doc_id, list_filter(string_split_regex(text, '[ \\n\\t\\r]+'), lambda w: w <> '') as toks from documents), range(1, len(toks) + 1) t(i)"


def feat_regex(spark, sf):
    f = X.feat_regex(_tokens(spark, sf), {"number": "^[0-9]+$", "caps": "^[A-Z]{2,}$", "mail": "@"})
    return f.groupBy("feature").agg(F.count("*").alias("n"), F.countDistinct("doc_id").alias("docs"))


FEAT_REGEX_SQL = f"with t as ({TOK_SQL}), f as (select doc_id, 'number' as feature from t where regexp_matches(token, '^[0-9]+$') union all select doc_id, 'caps' from t where regexp_matches(token, '^[A-Z]{{2,}}$') union all select doc_id, 'mail' from t where contains(token, '@')) select feature, count(*) as n, count(distinct doc_id) as docs from f group by 1"


def feat_dict(spark, sf):
    words = spark.createDataFrame([(w,) for w in INSULTS.split("|")], "w string")
    return X.feat_dictionary(_tokens(spark, sf), words, "w", "insult").select("doc_id", "pos", "feature")


FEAT_DICT_SQL = f"select doc_id, pos::int as pos, 'insult' as feature from ({TOK_SQL}) where lower(token) in ({', '.join(repr(w) for w in INSULTS.split('|'))})"


def feat_position(spark, sf):
    return X.feat_position(_tokens(spark, sf)).select("doc_id", "pos", "feature")


FEAT_POS_SQL = f"with t as ({TOK_SQL}), m as (select doc_id, max(pos) as last from t group by 1) select doc_id, pos::int as pos, 'first' as feature from t where pos = 0 union all select doc_id, last::int, 'final' from m"


def feat_word(spark, sf):
    t = _tokens(spark, sf)
    train, test = t.filter("doc_id % 5 <> 0"), t.filter("doc_id % 5 = 0")
    return X.feat_word(test, train).groupBy("doc_id").agg(F.count("*").alias("n"))


FEAT_WORD_SQL = f"with t as ({TOK_SQL}) select doc_id, count(*) as n from t where doc_id % 5 = 0 and lower(token) in (select lower(token) from t where doc_id % 5 <> 0) group by 1"


def feat_edge(spark, sf):
    t = T.tagged(_tokens(spark, sf), _shape_tag)
    return X.feat_edge(t).groupBy("feature").agg(F.count("*").alias("n"))


def _shape_tag(c):
    return F.when(c.rlike("^[a-z]+$"), "lower").when(c.rlike("^[A-Z][a-z]+$"), "title").otherwise("other")


_SHAPE_SQL = "case when regexp_matches(token, '^[a-z]+$') then 'lower' when regexp_matches(token, '^[A-Z][a-z]+$') then 'title' else 'other' end"
FEAT_EDGE_SQL = f"with t as (select doc_id, pos, {_SHAPE_SQL} as tag from ({TOK_SQL})), p as (select tag, lag(tag) over (partition by doc_id order by pos) as prev from t) select prev || '>' || tag as feature, count(*) as n from p where prev is not null group by 1"


def features_all(spark, sf):
    t = _tokens(spark, sf)
    f = X.extract_features(t, {"number": "^[0-9]+$"}, {"insult": (spark.createDataFrame([(w,) for w in INSULTS.split("|")], "w string"), "w")}, None, True)
    return f.groupBy("feature").agg(F.count("*").alias("n"))


FEAT_ALL_SQL = f"with t as ({TOK_SQL}) select 'number' as feature, count(*) as n from t where regexp_matches(token, '^[0-9]+$') having count(*) > 0 union all select feature, count(*) from ({FEAT_DICT_SQL}) group by 1 union all select feature, count(*) from ({FEAT_POS_SQL}) group by 1"


# chains --------------------------------------------------------------------------------------------------------------

def _emissions(tokens):
    tag = _shape_tag(F.col("token"))
    row = lambda k: F.array(*map(F.lit, map(float, EMIT[k])))
    s = F.when(tag == "lower", row("lower")).when(tag == "title", row("title")).otherwise(row("other"))
    return tokens.select("doc_id", "pos", s.alias("s"))


#: Whole short texts, all rows of their tables: passages for the forms that cost a job a token, and part names where the
#: exact answer lists every labeling. LONGEST bounds the recursion, which fails on a longer text.
LONGEST = 64


def _scores(spark, sf):
    return _emissions(X.tokenize(table(spark, sf, "benchmark"), "item_id", "text", r"[^ \n\t\r]+"))


def _names(spark, sf):
    return _emissions(X.tokenize(table(spark, sf, "part"), "p_partkey", "p_name", r"[^ \n\t\r]+"))


def _best(df):
    return df.select("doc_id", F.col("score").cast("long").alias("score"))


def viterbi_fold(spark, sf):
    return _best(C.viterbi_fold(C.pack(_scores(spark, sf)), TRANS))


def viterbi_kernel(spark, sf):
    return _best(C.viterbi_kernel(C.pack(_scores(spark, sf)), TRANS))


def viterbi_driver(spark, sf):
    return _best(C.viterbi_driver(_scores(spark, sf), TRANS))


def viterbi_window(spark, sf):
    return _best(C.viterbi_window(_scores(spark, sf), TRANS))


def viterbi_recursive(spark, sf):
    return _best(C.viterbi_recursive(spark, _scores(spark, sf), TRANS, LONGEST))


def viterbi_all_documents(spark, sf):
    """Every whole document by the numpy kernel, one row a document. A text's tokens stay in its row, so nothing is shuffled."""
    toks = F.regexp_extract_all("text", F.lit(r"([^ \n\t\r]+)"), F.lit(1))
    row = lambda k: F.array(*map(F.lit, map(float, EMIT[k])))
    e = F.transform(toks, lambda t: F.when(_shape_tag(t) == "lower", row("lower")).when(_shape_tag(t) == "title", row("title")).otherwise(row("other")))
    return _best(C.viterbi_kernel(table(spark, sf, "documents").select("doc_id", e.alias("e")), TRANS))


_STEP = ", ".join(f"'e{j}': e.e{j} + greatest({', '.join(f'v.e{k} + {int(TRANS[k, j])}' for k in range(LABELS))})" for j in range(LABELS))
_EMITS = ", ".join(f"'e{j}': (case {{c}} when 'lower' then {EMIT['lower'][j]} when 'title' then {EMIT['title'][j]} else {EMIT['other'][j]} end)::bigint" for j in range(LABELS))


def _emit_sql() -> str:
    return ", ".join(f"case {_SHAPE_SQL} when 'lower' then {EMIT['lower'][j]} when 'title' then {EMIT['title'][j]} else {EMIT['other'][j]} end as e{j}" for j in range(LABELS))


_NEXT = ", ".join(f"e.e{j} + greatest({', '.join(f'v{k} + {int(TRANS[k, j])}' for k in range(LABELS))})" for j in range(LABELS))


def _toks_sql(name: str, key: str, text: str) -> str:
    return TOK_SQL.replace("select doc_id, list_filter", f"select {key} as doc_id, list_filter").replace("split_regex(text", f"split_regex({text}").replace("from documents", f"from {name}")


VITERBI_SQL = f"""
with recursive e as materialized (select doc_id, pos, {_emit_sql()} from ({_toks_sql('benchmark', 'item_id', 'text')})),
r(doc_id, pos, v0, v1, v2) as (select doc_id, pos, e0, e1, e2 from e where pos = 0 union all select e.doc_id, e.pos, {_NEXT} from r join e on e.doc_id = r.doc_id and e.pos = r.pos + 1)
select doc_id, arg_max(greatest(v0, v1, v2), pos)::bigint as score from r group by 1"""


ALL_VITERBI_SQL = (
    "with t as (select doc_id, list_filter(string_split_regex(text, '[ \\n\\t\\r]+'), lambda w: w <> '') as toks from documents), "
    f"e as (select doc_id, list_transform(toks, lambda token: {{{{{_EMITS.format(c=_SHAPE_SQL)}}}}}) as es from t where len(toks) > 0), ".replace("{{", "{").replace("}}", "}")
    + f"r as (select doc_id, list_reduce(es, lambda v, e: {{{_STEP}}}) as v from e) select doc_id, greatest(v.e0, v.e1, v.e2)::bigint as score from r"
)


def viterbi_topk(spark, sf):
    """Scores of the three best labelings."""
    return C.viterbi_kernel(C.pack(_names(spark, sf)), TRANS, 3).select("doc_id", "rank", F.col("score").cast("long").alias("score"))


_L3 = "(select unnest([0, 1, 2]) as l)"
TOPK_SQL = f"""
with recursive e as materialized (select doc_id, pos, l, case l when 0 then e0 when 1 then e1 else e2 end as e from (select doc_id, pos, {_emit_sql()} from ({_toks_sql('part', 'p_partkey', 'p_name')})), {_L3}),
w(k, l, t) as (values {', '.join(f'({a}, {b}, {int(TRANS[a, b])})' for a in range(3) for b in range(3))}),
r(doc_id, pos, l, s) as (select doc_id, pos, l, e from e where pos = 0 union all select e.doc_id, e.pos, e.l, r.s + w.t + e.e from r join e on e.doc_id = r.doc_id and e.pos = r.pos + 1 join w on w.k = r.l and w.l = e.l),
z as (select *, max(pos) over (partition by doc_id) as last from r)
select doc_id, row_number() over (partition by doc_id order by s desc)::int as rank, s::bigint as score from z where pos = last qualify rank <= 3"""


def viterbi_paths_agree(spark, sf):
    """Fold, driver and window forms give the kernel's path, not its score alone."""
    s = _scores(spark, sf).persist()
    base = C.viterbi_kernel(C.pack(s), TRANS).select("doc_id", "path", "score")
    out = []
    for name, df in (("fold", C.viterbi_fold(C.pack(s), TRANS)), ("driver", C.viterbi_driver(s, TRANS)), ("window", C.viterbi_window(s, TRANS))):
        j = base.join(df.select("doc_id", F.col("path").alias("p2"), F.col("score").alias("s2")), "doc_id")
        out.append((name, j.filter((F.col("score") != F.col("s2")) | (F.col("path") != F.col("p2"))).count() == 0))
    s.unpersist()
    return spark.createDataFrame(out, "variant string, agrees boolean")


def forward_backward(spark, sf):
    """log Z of every chain, from exact sums over all labelings."""
    f = C.forward_backward(C.pack(_names(spark, sf)), TRANS)
    return f.groupBy("doc_id").agg(F.round(F.max("log_z"), 5).alias("log_z"))


LOGZ_SQL = TOPK_SQL.split("z as (")[0] + "z as (select *, max(pos) over (partition by doc_id) as last from r) select doc_id, round(ln(sum(exp(s))), 5) as log_z from z where pos = last group by 1"


def crf_loglik(spark, sf):
    """Log-likelihood of the labeling by shape: lower 0, title 1, other 2."""
    t = X.tokenize(table(spark, sf, "part"), "p_partkey", "p_name", r"[^ \n\t\r]+")
    tag = _shape_tag(F.col("token"))
    label = F.when(tag == "lower", 0).when(tag == "title", 1).otherwise(2)
    s = _emissions(t).join(t.select("doc_id", "pos", label.alias("label")), ["doc_id", "pos"])
    return C.log_likelihood(s, TRANS).select("doc_id", F.col("score").cast("long").alias("score"), F.round("loglik", 5).alias("loglik"))


_OWN = f"case {_SHAPE_SQL} when 'lower' then 0 when 'title' then 1 else 2 end"
LOGLIK_SQL = LOGZ_SQL.replace("select doc_id, round(ln(sum(exp(s))), 5) as log_z from z where pos = last group by 1", f"""
, y as (select doc_id, ln(sum(exp(s))) as log_z from z where pos = last group by 1), o as (select doc_id, pos, {_OWN} as l from ({_toks_sql('part', 'p_partkey', 'p_name')})),
b as (select o.doc_id, o.pos, e.e, w.t from o join e on e.doc_id = o.doc_id and e.pos = o.pos and e.l = o.l left join o p on p.doc_id = o.doc_id and p.pos = o.pos - 1 left join w on w.k = p.l and w.l = o.l),
c as (select doc_id, sum(e + coalesce(t, 0)) as score from b group by 1)
select doc_id, score::bigint as score, round(score - log_z, 5) as loglik from c join y using (doc_id)""")


def _sampled(spark, sf, sampler, **kw):
    p = C.pack(_scores(spark, sf)).persist()
    e = E.marginal_error(C.mcmc(p, TRANS, sampler, **kw), C.forward_backward(p, TRANS))
    return e.select((F.col("mean") < 0.05).alias("near_exact"))


def mcmc_gibbs(spark, sf):
    return _sampled(spark, sf, "gibbs", n_iter=300, burn_in=50)


def mcmc_mh(spark, sf):
    return _sampled(spark, sf, "mh", n_iter=800, burn_in=100)


def mcmc_chains(spark, sf):
    """Four chains per document: their spread is small where they have mixed."""
    p = C.pack(_scores(spark, sf))
    return C.mcmc(p, TRANS, "gibbs", n_iter=300, burn_in=50, chains=4).agg((F.percentile("r_hat", 0.9) < 1.2).alias("mixed"))


def mcmc_coordination(spark, sf):
    """Per-document chains and driver-coordinated sweeps estimate the same marginals."""
    p = C.pack(_scores(spark, sf)).persist()
    exact = C.forward_backward(p, TRANS)
    d = E.marginal_error(C.mcmc_driver(p, TRANS, 40, 5), exact).first()
    w = E.marginal_error(C.mcmc(p, TRANS, "gibbs", n_iter=40, burn_in=5), exact).first()
    return spark.createDataFrame([(d["mean"] < 0.12, w["mean"] < 0.12)], "driver_near boolean, window_near boolean")


def crf_train(spark, sf):
    """Trained on four fifths of the documents; on the rest, token accuracy beats the most frequent tag, and the loss falls."""
    d = table(spark, sf, "documents")
    train, test = (T.tag_blocks(d.filter(f), "doc_id", "text", T.pos_tag_rules, T.POS, 1024) for f in ("doc_id % 5 <> 0", "doc_id % 5 = 0"))
    m = T.train_tagger(train, T.POS, 1024, 3)
    got = T.apply_tagger(test, m.state).select(F.explode(F.arrays_zip("path", "label")).alias("t")).groupBy("t.path", "t.label").agg(F.count("*").alias("n"))
    n, hit, by = 0, 0, [0] * len(T.POS)
    for r in got.collect():  # a row for each pair of labels
        n, hit, by[r["label"]] = n + r["n"], hit + r["n"] * (r["path"] == r["label"]), by[r["label"]] + r["n"]
    acc, top = hit / max(1, n), max(by) / max(1, n)
    losses = [r["loss"] for r in m.log.rows]
    return spark.createDataFrame([(acc > top, acc > 0.85, losses[-1] < losses[0])], "beats_majority boolean, above_85 boolean, loss_falls boolean")


def hmm_counts(spark, sf):
    _, tr = C.hmm_fit(T.tagged(_tokens(spark, sf), _shape_tag))
    return tr.select("prev", "tag", F.round("logp", 6).alias("logp"))


HMM_SQL = f"with t as (select doc_id, pos, {_SHAPE_SQL} as tag from ({TOK_SQL})), p as (select coalesce(lag(tag) over (partition by doc_id order by pos), '^') as prev, tag from t), c as (select prev, tag, count(*) as n from p group by all) select prev, tag, round(ln((n + 0.1::double) / (sum(n) over (partition by prev) + 0.1::double * 3)), 6) as logp from c"


# tasks ---------------------------------------------------------------------------------------------------------------


def pos_tags(spark, sf):
    return T.tagged(_tokens(spark, sf), T.pos_tag_rules).groupBy("tag").agg(F.count("*").alias("n"))


_FW = ", ".join(repr(w) for w in T.FUNCTION_WORDS)
POS_SQL = f"select case when regexp_matches(token, '^[0-9][0-9.,]*$') then 'NUM' when not regexp_matches(token, '[\\p{{L}}0-9]') then 'PUNCT' when lower(token) in ({_FW}) then 'FUNC' when regexp_matches(token, '^[^\\p{{Ll}}]*\\p{{Lu}}{{2}}[^\\p{{Ll}}]*$') then 'CAPS' when regexp_matches(token, '^\\p{{Lu}}') then 'TITLE' else 'WORD' end as tag, count(*) as n from ({TOK_SQL}) group by 1"


def ner_entities(spark, sf):
    """Spans of entity tags by rule."""
    return C.spans(T.tagged(_tokens(spark, sf), T.entity_rules)).select("doc_id", "start", "kind", "text")


_ENT_CASE = "case " + " ".join(f"when regexp_matches(token, '{p}') then '{k}'" for k, p in T.ENTITIES.items()) + " else 'O' end"
NER_SQL = f"""
with t as (select doc_id, pos, token, {_ENT_CASE} as tag from ({TOK_SQL})), c as (select *, (coalesce(lag(tag) over w, '') <> tag)::int as ch from t window w as (partition by doc_id order by pos)),
i as (select *, sum(ch) over (partition by doc_id order by pos) as isl from c) select doc_id, min(pos)::int as start, tag as kind, string_agg(token, ' ' order by pos) as text from i where tag <> 'O' group by doc_id, isl, tag"""


def ner_model(spark, sf):
    """A trained tagger finds entities of held-out documents; sampled and best labelings both score."""
    labels = ("O", *T.ENTITIES)
    d = table(spark, sf, "documents")
    train, test = (T.tag_blocks(d.filter(f), "doc_id", "text", T.entity_rules, labels) for f in ("doc_id % 3 <> 0", "doc_id % 3 = 0"))
    m = T.train_tagger(train, labels, 2048, 4, 0.5)
    out = []
    for method in ("viterbi", "mcmc"):
        got = stage(C.label_spans(T.apply_tagger(test, m.state, method), labels), "spans")
        r = E.prf(got.filter("found"), got.filter("not found"), ["doc_id", "start", "kind"]).first()
        out.append((method, bool((r["f1"] or 0) > 0.5)))
    return spark.createDataFrame(out, "method string, f1_above_half boolean")


def entity_resolution(spark, sf):
    """Parts whose names match an entity's name approximately."""
    name = "antique almond"
    p = table(spark, sf, "part").select("p_partkey", "p_name")
    first = p.orderBy("p_partkey").first()["p_name"] or name
    return T.resolve(p, "p_partkey", "p_name", first, "match", 0.5).select(F.col("doc_id").alias("p_partkey"), F.round("similarity", 6).alias("similarity"))


_GRAMS = "list_distinct(list_transform(range(1, greatest(length({c}) - 1, 1)), lambda i: substring(lower({c}), i::int, 3)))"


def _grams(c: str) -> str:
    return f"(case when length({c}) >= 3 then {_GRAMS.format(c=c)} else [] end)"


RESOLVE_SQL = f"""
with q as (select p_name as q from part order by p_partkey limit 1), g as (select p_partkey, {_grams('p_name')} as g, {_grams('q')} as h from part, q),
s as (select p_partkey, len(list_intersect(g, h)) / (len(g) + len(h) - len(list_intersect(g, h)))::double as s from g) select p_partkey, round(s, 6) as similarity from s where s >= 0.5"""


def entity_resolution_mcmc(spark, sf):
    """Copies of one part name, one for each brand that has it, are put into one entity by sampling."""
    names = table(spark, sf, "part").select("p_name", F.concat_ws("|", "p_name", "p_brand").alias("k")).distinct().persist()
    r = T.resolve(names, "k", "p_name", method="mcmc", threshold=0.9)
    j = r.join(names.select(F.col("k").alias("mention"), F.col("p_name").alias("a")), "mention").join(names.select(F.col("k").alias("entity"), F.col("p_name").alias("b")), "entity")
    return j.agg((F.avg((F.col("a") == F.col("b")).cast("double")) >= 0.99).alias("pure"))


# grams ---------------------------------------------------------------------------------------------------------------


def trigram_index(spark, sf):
    """The number of passages that hold each gram."""
    return X.build_qgram_index(table(spark, sf, "benchmark"), "item_id", "text").groupBy("gram").agg(F.count("*").alias("n"))


TRIGRAM_SQL = f"select gram, count(*) as n from (select unnest({_grams('text')}) as gram from benchmark) group by 1"


def approx_match_part(spark, sf):
    first = table(spark, sf, "part").orderBy("p_partkey").first()["p_name"]
    return X.approx_match(table(spark, sf, "part"), "p_partkey", "p_name", first, 0.3).select("doc_id", F.round("similarity", 6).alias("similarity"))


APPROX_SQL = RESOLVE_SQL.replace("p_partkey, round(s, 6)", "p_partkey as doc_id, round(s, 6)").replace("s >= 0.5", "s >= 0.3")


def _phrase(spark, sf):
    return " ".join(table(spark, sf, "documents").filter("length(text) > 2000").orderBy("doc_id").first()["text"].split()[10:15])


def approx_match_window(spark, sf):
    """Documents with a window of about as many words that is like a phrase of one of them, and the best similarity."""
    m = X.approx_match(table(spark, sf, "documents"), "doc_id", "text", _phrase(spark, sf), 0.6, "window")
    return m.select("doc_id", F.round("similarity", 6).alias("similarity"))


def _grams_of(c: str) -> str:
    return f"list_distinct(list_transform(range(1, length({c}) - 1), lambda i: substring({c}, i::int, 3)))"


WINDOW_SQL = f"""
with d as materialized (select doc_id, text, list_filter(string_split_regex(lower(text), '\\s+'), lambda w: w <> '') as w from documents),
q as materialized (select {_grams_of('p')} as h from (select array_to_string(w[11:15], ' ') as p from d where length(text) > 2000 order by doc_id limit 1)),
f as (select g, (select sum(length(text) - length(replace(lower(text), g, ''))) from d) as f from (select unnest(h) as g from q)),
r as materialized (select list(g order by f, g)[1 : count(*) - ceil(0.6 * count(*))::int + 1] as r, list(g) as h from f),
x as (select doc_id, array_to_string(w[i : i + k - 1], ' ') as t from d, (select unnest([4, 5, 6]) as k), range(1, greatest(len(w) - k + 1, 1) + 1) r(i)),
y as materialized (select doc_id, h, {_grams_of('t')} as g from x, r where length(t) >= 3 and len(list_filter(r, lambda g: contains(t, g))) > 0),
s as (select doc_id, len(list_intersect(g, h)) as m, len(g) + len(h) as n from y)
select doc_id, round(max(m / (n - m)::double), 6) as similarity from s group by 1 having max(m / (n - m)::double) >= 0.6"""


def approx_match_doc(spark, sf):
    """Documents whose whole gram set is like that of the least document without near copies of it."""
    q = table(spark, sf, "documents").filter("length(text) > 2000").orderBy("doc_id").first()["text"]
    m = X.approx_match(table(spark, sf, "documents"), "doc_id", "text", q, 0.4)
    return m.select("doc_id", F.round("similarity", 6).alias("similarity"))


MATCH_DOC_SQL = f"""
with g as materialized (select doc_id, length(text) as n, {_grams('text')} as g from documents), q as materialized (select g as h from g where n > 2000 order by doc_id limit 1),
i as materialized (select doc_id, len(list_intersect(g, h)) as i, len(g) + len(h) as n from g, q) select doc_id, round(i / (n - i)::double, 6) as similarity from i where i / (n - i)::double >= 0.4"""


def gram_measures(spark, sf):
    """Jaccard, Dice and edit distance of part names and brands."""
    g = lambda c: F.array_distinct(X.qgrams(F.col(c), 2))
    p = table(spark, sf, "part").select("p_partkey", "p_name", "p_type")
    return p.select("p_partkey", F.round(X.gram_similarity(g("p_name"), g("p_type")), 6).alias("jaccard"), F.round(X.gram_dice(g("p_name"), g("p_type")), 6).alias("dice"), X.within_edits(F.col("p_name"), F.col("p_type"), 18).alias("near"))


_G2 = "list_distinct(list_transform(range(1, length({c})), lambda i: substring(lower({c}), i::int, 2)))"
MEASURES_SQL = f"""
with g as (select p_partkey, p_name, p_type, {_G2.format(c='p_name')} as a, {_G2.format(c='p_type')} as b from part), i as (select *, len(list_intersect(a, b)) as n from g)
select p_partkey, round(n / (len(a) + len(b) - n)::double, 6) as jaccard, round(2 * n / (len(a) + len(b))::double, 6) as dice, levenshtein(p_name, p_type) <= 18 as near from i"""


def approx_join_benchmark(spark, sf):
    """Documents that hold at least 95 per cent of a passage's grams."""
    r = X.contained_passages(table(spark, sf, "documents"), table(spark, sf, "benchmark"), "doc_id", "text", "item_id", "text", 0.95)
    return r.select("doc_id", "item_id", F.round("share", 6).alias("share"))


JOIN_SQL = f"""
with d as materialized (select doc_id, unnest({_grams('text')}) as gram from documents), b as materialized (select item_id, unnest(g) as gram, len(g) as n from (select item_id, {_grams('text')} as g from benchmark))
select doc_id, item_id, round(count(*) / any_value(n)::double, 6) as share from d join b using (gram) group by all having count(*) / any_value(n)::double >= 0.95"""


def approx_join_names(spark, sf):
    """Pairs of distinct part names at a similarity of 0.6."""
    p = table(spark, sf, "part").select("p_name").distinct()
    j = X.approx_join(p.withColumnRenamed("p_name", "a"), p.withColumnRenamed("p_name", "b"), "a", "a", "b", "b", 0.6)
    return j.select("left_id", "right_id", F.round("similarity", 6).alias("similarity"))


NAMES_SQL = f"""
with p as (select distinct p_name as n, {_grams('p_name')} as g from part), s as (select a.n as left_id, b.n as right_id, len(list_intersect(a.g, b.g)) / (len(a.g) + len(b.g) - len(list_intersect(a.g, b.g)))::double as s from p a, p b)
select left_id, right_id, round(s, 6) as similarity from s where s >= 0.6"""


def term_index_lookup(spark, sf):
    idx = X.build_term_index(_tokens(spark, sf))
    return X.lookup_terms(idx, ["the", "and", "of"], "and").select("doc_id")


LOOKUP_SQL = f"select doc_id from ({TOK_SQL}) where lower(token) in ('the', 'and', 'of') group by 1 having count(distinct lower(token)) = 3"


def pages_text(spark, sf):
    p = table(spark, sf, "pages").select("page_id", X.strip_html(F.col("html")).alias("t"))
    return p.select("page_id", F.length("t").alias("n"), F.size(F.split("t", " ")).alias("words"))


PAGES_SQL = r"""
with t as (select page_id, trim(regexp_replace(regexp_replace(regexp_replace(html, '(?is)<(script|style)[^>]*>.*?</(script|style)>', ' ', 'g'), '<[^>]*>', ' ', 'g'), '[ \t\n\x0b\f\r]+', ' ', 'g')) as t from pages)
select page_id, length(t)::int as n, len(string_split(t, ' '))::int as words from t"""


def conversations_roles(spark, sf):
    return X.tokenize(table(spark, sf, "conversations").withColumn("k", F.concat_ws("/", "conv_id", "turn")), "k", "text", r"[^ \n\t\r]+").groupBy("doc_id").agg(F.count("*").alias("n"))


CONV_SQL = "select conv_id || '/' || turn as doc_id, len(list_filter(string_split_regex(text, '[ \\n\\t\\r]+'), lambda w: w <> ''))::bigint as n from conversations where len(list_filter(string_split_regex(text, '[ \\n\\t\\r]+'), lambda w: w <> '')) > 0"


QUERIES = {f.__name__: f for f in (
    feat_regex, feat_dict, feat_position, feat_word, feat_edge, features_all, viterbi_fold, viterbi_kernel, viterbi_driver, viterbi_window, viterbi_recursive, viterbi_all_documents, viterbi_topk,
    viterbi_paths_agree, forward_backward, crf_loglik, mcmc_gibbs, mcmc_mh, mcmc_chains, mcmc_coordination, crf_train, hmm_counts, pos_tags, ner_entities, ner_model, entity_resolution, entity_resolution_mcmc, trigram_index,
    approx_match_part, approx_match_doc, approx_match_window, gram_measures, approx_join_benchmark, approx_join_names, term_index_lookup, pages_text, conversations_roles,
)}

ORACLE = {
    "feat_regex": FEAT_REGEX_SQL, "feat_dict": FEAT_DICT_SQL, "feat_position": FEAT_POS_SQL, "feat_word": FEAT_WORD_SQL, "feat_edge": FEAT_EDGE_SQL, "features_all": FEAT_ALL_SQL,
    **{f"viterbi_{v}": VITERBI_SQL for v in ("fold", "kernel", "driver", "window", "recursive")}, "viterbi_all_documents": ALL_VITERBI_SQL, "viterbi_topk": TOPK_SQL,
    "viterbi_paths_agree": "select unnest(['fold', 'driver', 'window']) as variant, true as agrees", "forward_backward": LOGZ_SQL, "crf_loglik": LOGLIK_SQL,
    "mcmc_gibbs": "select true as near_exact", "mcmc_mh": "select true as near_exact", "mcmc_chains": "select true as mixed", "mcmc_coordination": "select true as driver_near, true as window_near",
    "crf_train": "select true as beats_majority, true as above_85, true as loss_falls", "hmm_counts": HMM_SQL, "pos_tags": POS_SQL, "ner_entities": NER_SQL,
    "ner_model": "select unnest(['viterbi', 'mcmc']) as method, true as f1_above_half", "entity_resolution": RESOLVE_SQL, "entity_resolution_mcmc": "select true as pure",
    "trigram_index": TRIGRAM_SQL, "approx_match_part": APPROX_SQL, "approx_match_window": WINDOW_SQL, "approx_match_doc": MATCH_DOC_SQL, "gram_measures": MEASURES_SQL, "pages_text": PAGES_SQL, "approx_join_benchmark": JOIN_SQL, "approx_join_names": NAMES_SQL,
    "term_index_lookup": LOOKUP_SQL, "conversations_roles": CONV_SQL,
}
