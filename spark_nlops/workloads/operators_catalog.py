"""Driver queries of the reference operators, cascades, vectors, extraction, baselines and measures."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import measures
from ..baselines import budget_filter as budget
from ..baselines import factcheck, rewriter, rowwise
from ..baselines.compiled import guess_retrieve_rerank
from ..functions import text as tx
from ..models.rules import LookupModel, LookupText, RuleModel
from ..operators.cluster import grouping_objective, nl_classify, nl_cluster
from ..operators.filter import nl_filter, route
from ..operators.join import nl_join
from ..operators.project import nl_extract, nl_project
from ..operators.rank import nl_rank
from ..operators.reduce import nl_reduce, pack
from ..operators.search import nl_search, nl_similar_join, with_similarity
from ..relational.surround import JUNK_SQL
from ..result import SampleSpec
from ..sources.tables import read_table
from ..staging import shared_folder, staged
from ..stats import bounds, calibrate, cuts, sampling
from ..stats.hashing import uniform_sql
from ..vectors.containment import containment_groups
from ..vectors.embed import HashedNgrams
from ..vectors.index import build_text_index, load_text_index
from ..vectors.kmeans import lloyd_step
from . import common as w

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def put(f):
        QUERIES[name] = f
        if sql is not None:
            SQL[name] = sql
        return f

    return put


def docs(s, d, *columns) -> DataFrame:
    return read_table(s, d, "documents", list(columns) or None)


# --- reference operators -----------------------------------------------------------------
INSULT_SQL = f"regexp_matches(lower(text), '(^|[^a-z])({'|'.join(w.INSULTS)})($|[^a-z])')"


@query("filter_reference_junk", f"SELECT doc_id, lang FROM documents WHERE {JUNK_SQL}")
def _(s, d):
    return nl_filter(docs(s, d), w.JUNK, w.junk_oracle(), plan="reference").df.select("doc_id", "lang")


@query("filter_reference_toxic", f"SELECT doc_id FROM documents WHERE {INSULT_SQL}")
def _(s, d):
    return nl_filter(docs(s, d, "doc_id", "text"), w.TOXIC, w.toxic_oracle(), plan="reference").df.select("doc_id")


@query("filter_lookup_labels", "SELECT doc_id FROM documents WHERE doc_id IN (SELECT doc_id FROM labels WHERE toxic = 1)")
def _(s, d):
    truth = LookupModel(read_table(s, d, "labels"), "doc_id", "toxic")
    return nl_filter(docs(s, d, "doc_id", "text"), w.TOXIC, truth, plan="reference").df.select("doc_id")


PAIRS_SQL = "SELECT d.doc_id, b.item_id FROM documents d JOIN benchmark b ON contains(d.text, b.text)"


def _contains(s, d, how, **more):
    return nl_join(docs(s, d, "doc_id", "text"), read_table(s, d, "benchmark"), w.CONTAINS, w.contains_oracle(), left_key="doc_id", right_key="item_id", how=how, **more)


@query("join_reference_contains", PAIRS_SQL)
def _(s, d):
    return _contains(s, d, "inner").df.select("doc_id", F.col("right_item_id").alias("item_id"))


@query("join_left", f"SELECT d.doc_id, p.item_id FROM documents d LEFT JOIN ({PAIRS_SQL}) p ON p.doc_id = d.doc_id")
def _(s, d):
    return _contains(s, d, "left").df.select("doc_id", F.col("right_item_id").alias("item_id"))


@query("join_semi", f"SELECT doc_id FROM documents WHERE doc_id IN (SELECT doc_id FROM ({PAIRS_SQL}))")
def _(s, d):
    return _contains(s, d, "semi").df.select("doc_id")


@query("join_anti", f"SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM ({PAIRS_SQL}))")
def _(s, d):
    return _contains(s, d, "anti").df.select("doc_id")


def _html_sql(column: str) -> str:
    out = column
    for pattern in (r"(?is)<script.*?</script>", r"(?is)<style.*?</style>", r"(?s)<!--.*?-->", r"(?s)<[^>]*>"):
        out = f"regexp_replace({out}, '{pattern}', ' ', 'g')"
    for entity, sign in (("&nbsp;", " "), ("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "''"), ("&amp;", "&")):
        out = f"replace({out}, '{entity}', '{sign}')"
    return f"trim(regexp_replace({out}, '\\s+', ' ', 'g'))"


PAGES_SQL = f"SELECT page_id, doc_id FROM (SELECT page_id, {_html_sql('html')} AS body FROM pages) JOIN (SELECT doc_id, trim(regexp_replace(text, '\\s+', ' ', 'g')) AS whole FROM documents) ON contains(body, whole)"


def page_bodies(s, d) -> DataFrame:
    return staged(read_table(s, d, "pages").select("page_id", tx.html_to_text(F.col("html")).alias("body")), "pages")


@query("join_page_document", PAGES_SQL)
def _(s, d):
    """Every page with every document whose whole text it holds, white space aside."""
    wholes = staged(docs(s, d, "doc_id", "text").select("doc_id", tx.squeeze(F.col("text")).alias("whole")), "wholes")
    rule = RuleModel(predicate="contains(left_body, right_whole)", holds=("left_body", "right_whole"))
    out = nl_join(page_bodies(s, d), wholes, "{body:left} was made from {whole:right}", rule, left_key="page_id", right_key="doc_id")
    return out.df.select("page_id", F.col("right_doc_id").alias("doc_id"))


@query("join_page_document_rewritten", PAGES_SQL)
def _(s, d):
    """The same pairs by the rewritten rule itself: candidates by chosen hashes, whole texts verify."""
    bodies = page_bodies(s, d)
    wholes = staged(docs(s, d, "doc_id", "text").select("doc_id", tx.squeeze(F.col("text")).alias("whole")).filter("whole IS NOT NULL"), "wholes")
    met, copies = containment_groups(bodies, wholes, "page_id", "body", "doc_id", "whole")
    met = met.join(wholes, F.col("rk") == F.col("doc_id")).join(bodies, F.col("lk") == F.col("page_id"))
    held = staged(met.filter("contains(body, whole)").select("page_id", F.col("rk").alias("first")), "held")
    return held.join(copies, "first").select("page_id", F.col("rk").alias("doc_id"))


@query("self_join_copies", "SELECT doc_id, first_id FROM (SELECT doc_id, min(doc_id) OVER (PARTITION BY text) AS first_id FROM documents) WHERE doc_id > first_id")
def _(s, d):
    """Copies of a text, each tied to the first one: one aggregation and one join by hash, no pairs within groups."""
    marked = docs(s, d, "doc_id", "text").select("doc_id", F.sha2("text", 256).alias("h"))
    first = marked.groupBy("h").agg(F.min("doc_id").alias("first_id"))
    return marked.join(first, "h").filter("doc_id > first_id").select("doc_id", "first_id")


# --- ranking ---------------------------------------------------------------------------
PRICE = "the one of {p_name} and its like that sells at the highest price"
BY_PRICE = "a.p_retailprice > b.p_retailprice OR (a.p_retailprice = b.p_retailprice AND a.p_partkey < b.p_partkey)"
K = 10
TOP_PRICE_SQL = f"SELECT p_partkey, p_retailprice, (row_number() OVER (ORDER BY p_retailprice DESC, p_partkey))::INTEGER AS rank FROM part ORDER BY p_retailprice DESC, p_partkey LIMIT {K}"


def by_price(a: dict, b: dict) -> bool:
    return (a["p_retailprice"], -a["p_partkey"]) > (b["p_retailprice"], -b["p_partkey"])


def price_rank(s, d, algorithm: str, model=None, k: int = K, **more):
    part = read_table(s, d, "part", ["p_partkey", "p_name", "p_retailprice"])
    if more.get("similarity"):
        part = staged(with_similarity(part, "p_name", "highest price", HashedNgrams(1, 256)), "part")
    return nl_rank(part, PRICE, k, model or RuleModel(compare=BY_PRICE), key="p_partkey", algorithm=algorithm, **more)


for _name, _algorithm, _more in (
    ("rank_quickselect", "quickselect", {}),
    ("rank_quickselect_pivot_sim", "quickselect", {"pivot": "similarity", "similarity": "sim"}),
    ("rank_heap", "heap", {"compare": by_price}),
    ("rank_quadratic", "quadratic", {}),
    ("rank_pointwise", "pointwise", {"score": "p_retailprice"}),
    ("rank_listwise", "listwise", {"score": "p_retailprice"}),
):

    @query(_name, TOP_PRICE_SQL)
    def _(s, d, algorithm=_algorithm, more=_more):
        return price_rank(s, d, algorithm, **more).df.select("p_partkey", "p_retailprice", "rank")


UNIGRAMS = HashedNgrams(1, 256)
TRIGRAMS = HashedNgrams(3, 1024)


def sims_sql(left: str, lkey: str, ltext: str, right: str, rkey: str, rtext: str, embedder: HashedNgrams = UNIGRAMS) -> str:
    """All pairs (lk, rk, sim) with cosine of hashed n-grams, zeros included."""
    return f"""SELECT l.k AS lk, r.k AS rk, coalesce(sim, 0.0) AS sim FROM (SELECT {lkey} AS k FROM {left}) l CROSS JOIN (SELECT {rkey} AS k FROM {right}) r
LEFT JOIN (SELECT a.key AS lk, b.key AS rk, round(sum(a.w * b.w), 9) AS sim FROM ({embedder.sql(left, lkey, ltext)}) a JOIN ({embedder.sql(right, rkey, rtext)}) b USING (dim) GROUP BY ALL) p ON p.lk = l.k AND p.rk = r.k"""


QUESTION = "the and of highest price"
QUESTION_SQL = f"(SELECT 0 AS qid, '{QUESTION}' AS q)"


@query("rank_rerank", f"""WITH sims AS ({sims_sql('part', 'p_partkey', 'p_name', QUESTION_SQL, 'qid', 'q')}),
near AS (SELECT lk FROM sims ORDER BY sim DESC, lk LIMIT 100)
SELECT p_partkey, p_retailprice, (row_number() OVER (ORDER BY p_retailprice DESC, p_partkey))::INTEGER AS rank FROM part JOIN near ON lk = p_partkey ORDER BY p_retailprice DESC, p_partkey LIMIT {K}""")
def _(s, d):
    part = staged(with_similarity(read_table(s, d, "part", ["p_partkey", "p_name", "p_retailprice"]), "p_name", QUESTION, UNIGRAMS), "part")
    return nl_rank(part, PRICE, K, key="p_partkey", algorithm="rerank", similarity="sim", score="p_retailprice", retrieve=100).df.select("p_partkey", "p_retailprice", "rank")


@query("rank_grouped_lang", f"SELECT doc_id, lang, (row_number() OVER (PARTITION BY lang ORDER BY n_chars DESC, doc_id))::INTEGER AS rank FROM documents QUALIFY rank <= {K}")
def _(s, d):
    longer = RuleModel(compare="a.n_chars > b.n_chars OR (a.n_chars = b.n_chars AND a.doc_id < b.doc_id)")
    return nl_rank(docs(s, d, "doc_id", "lang", "n_chars"), "the longest by {n_chars}", K, longer, key="doc_id", by=["lang"]).df.select("doc_id", "lang", "rank")


# --- reduction -------------------------------------------------------------------------
TERMS = RuleModel(reducer="array_join(array_sort(array_distinct(filter(flatten(transform(parts, p -> split(p, ' '))), t -> t <> ''))), ' ')", model_id="term-union")
JOINED = RuleModel(reducer="array_join(parts, ' | ')", model_id="concatenation")
FIRST_WORD = "lower(regexp_extract(text, '([A-Za-z]+)', 1))"


@query("reduce_tree", f"SELECT string_agg(DISTINCT t, ' ' ORDER BY t) AS reduced, (SELECT count(*) FROM documents WHERE text IS NOT NULL) AS n_sources FROM (SELECT {FIRST_WORD} AS t FROM documents) WHERE t <> ''")
def _(s, d):
    df = docs(s, d, "doc_id", "text").select("doc_id", F.expr(FIRST_WORD).alias("term"))
    out = nl_reduce(df, "all terms of {term}", TERMS, key="doc_id", text="term", fanin=64)
    return out.df.select("reduced", "n_sources")


@query("reduce_grouped", f"SELECT source, coalesce(string_agg(DISTINCT t, ' ' ORDER BY t) FILTER (t <> ''), '') AS reduced FROM (SELECT source, {FIRST_WORD} AS t FROM documents) GROUP BY source")
def _(s, d):
    df = docs(s, d, "doc_id", "source", "text").select("doc_id", "source", F.expr(FIRST_WORD).alias("term"))
    return nl_reduce(df, "all terms of {term}", TERMS, key="doc_id", text="term", by=["source"]).df.select("source", "reduced")


TALK_SQL = "SELECT conv_id, string_agg(text, ' | ' ORDER BY turn) AS reduced FROM conversations GROUP BY conv_id"


@query("reduce_fold", TALK_SQL)
def _(s, d):
    return nl_reduce(read_table(s, d, "conversations"), "continue with {text}", JOINED, key="turn", text="text", by=["conv_id"], pattern="fold").df.select("conv_id", "reduced")


@query("reduce_partitioned_order", TALK_SQL)
def _(s, d):
    """An order-sensitive reducer made right by a partitioner: one bucket for each conversation, in the order of turns."""
    talk = read_table(s, d, "conversations")
    out = nl_reduce(talk, "join {text}", JOINED, key="turn", text="text", by=["conv_id"], fanin=3, token_budget=100_000, partitioner=lambda df: (F.lit(0), F.col("turn")))
    return out.df.select("conv_id", "reduced")


WORDS_SQL = "list_filter(string_split_regex(lower(text), '\\s+'), lambda x: x <> '')"


@query("reduce_packing_bins", f"""WITH t AS (SELECT source, doc_id, greatest(len({WORDS_SQL}), 1) AS n FROM documents), c AS (
SELECT *, ((sum(n) OVER (PARTITION BY source ORDER BY doc_id) - n) // 2048)::BIGINT AS cut FROM t)
SELECT doc_id, source, cut, ((row_number() OVER (PARTITION BY source, cut ORDER BY doc_id) - 1) // 8)::BIGINT AS piece FROM c""")
def _(s, d):
    df = docs(s, d, "doc_id", "source", "text").select("doc_id", "source", F.greatest(tx.token_estimate(F.col("text")), F.lit(1)).alias("n"))
    out = pack(df, [], "source", "doc_id", "n", 2048, 8)
    return out.select("doc_id", "source", F.col("bin.cut").cast("bigint").alias("cut"), F.col("bin.piece").cast("bigint").alias("piece"))


# --- groups ----------------------------------------------------------------------------
#: Frequent words of four languages (fixed values).
STOPS = {"de": ("der", "die", "und", "das", "ist", "nicht", "mit", "zu"), "en": ("the", "and", "of", "to", "in", "is", "that", "was"), "es": ("el", "la", "que", "de", "los", "en", "y", "las"), "fr": ("le", "les", "et", "des", "est", "dans", "une", "pour")}
LANGUAGE = "the language of {text}"
STOP_RULES = {k: f"size(filter(split(lower(text), ' '), w -> w IN ({', '.join(repr(x) for x in v)})))" for k, v in STOPS.items()}
STOP_SQL = {k: f"len(list_filter(string_split(lower(text), ' '), lambda w: w IN ({', '.join(repr(x) for x in v)})))" for k, v in STOPS.items()}
_BEST = f"greatest({', '.join(STOP_SQL.values())})"
CLASSIFY_SQL = "SELECT doc_id, CASE " + " ".join(f"WHEN {STOP_SQL[k]} = {_BEST} THEN '{k}'" for k in sorted(STOPS)) + " END AS group_label FROM documents"


def language_oracle() -> RuleModel:
    return RuleModel(classifier=STOP_RULES, model_id="stop-words")


@query("classify_reference", CLASSIFY_SQL)
def _(s, d):
    return nl_classify(docs(s, d, "doc_id", "text"), LANGUAGE, list(STOPS), language_oracle(), plan="reference").df.select("doc_id", "group_label")


@query("group_given_labels", CLASSIFY_SQL)
def _(s, d):
    m = language_oracle()
    return nl_cluster(docs(s, d, "doc_id", "text"), LANGUAGE, 4, key="doc_id", projector=m, embedder=UNIGRAMS, reducer=TERMS, oracle=m, labels=list(STOPS)).df.select("doc_id", "group_label")


@query("group_objective", f"SELECT sum({_BEST})::DOUBLE AS objective, count(*) AS n_rows FROM documents")
def _(s, d):
    return grouping_objective(docs(s, d, "doc_id", "text"), STOP_RULES)


CENTER_TEXT = {k: " ".join(v) for k, v in STOPS.items()}
CENTER_SQL = "(VALUES " + ", ".join(f"({i}, '{k}', '{CENTER_TEXT[k]}')" for i, k in enumerate(sorted(STOPS))) + ") AS c(cid, name, words)"
#: Similarity above which the nearest label is taken in the route query.
ROUTE_CUT = 0.35


def label_centers() -> dict[str, list[float]]:
    return {k: UNIGRAMS.many([v])[0].tolist() for k, v in CENTER_TEXT.items()}


@query("classify_cascade_routes", f"""WITH sims AS ({sims_sql('documents', 'doc_id', 'text', '(SELECT * FROM ' + CENTER_SQL + ')', 'cid', 'words')}),
best AS (SELECT lk, rk, sim FROM sims QUALIFY row_number() OVER (PARTITION BY lk ORDER BY sim DESC, rk) = 1)
SELECT lk AS doc_id, name AS near, CASE WHEN sim >= {ROUTE_CUT} THEN 'accept' ELSE 'ask' END AS route FROM best JOIN {CENTER_SQL} ON cid = rk""")
def _(s, d):
    from ..vectors.similarity import similar_pairs

    names = sorted(STOPS)
    centers = s.createDataFrame([(i, label_centers()[k]) for i, k in enumerate(names)], "cid long, v array<double>")
    own = UNIGRAMS.embed(docs(s, d, "doc_id", "text"), "text", "v")
    near = similar_pairs(own, centers, "doc_id", "v", "cid", "v", k=1)
    name = F.element_at(F.array(*[F.lit(k) for k in names]), F.col("rk").cast("int") + 1)
    return near.select(F.col("lk").alias("doc_id"), name.alias("near"), F.when(F.col("sim") >= ROUTE_CUT, "accept").otherwise("ask").alias("route"))


@query("kmeans_deterministic_step", """WITH v AS (SELECT vec_id, embedding::DOUBLE[] AS e FROM embeddings), c AS (SELECT (row_number() OVER (ORDER BY vec_id) - 1) AS c, e AS m FROM v ORDER BY vec_id LIMIT 4),
near AS (SELECT vec_id, e, c FROM v CROSS JOIN c QUALIFY row_number() OVER (PARTITION BY vec_id ORDER BY round(list_distance(e, m), 9), c) = 1)
SELECT c::BIGINT AS cluster, i::BIGINT AS place, round(avg(x), 6) AS value FROM (SELECT c, unnest(e) AS x, generate_subscripts(e, 1) - 1 AS i FROM near) GROUP BY ALL""")
def _(s, d):
    e = read_table(s, d, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("v"))
    start = [list(r["v"]) for r in e.orderBy("vec_id").limit(4).collect()]
    moved = lloyd_step(e, "v", start)
    return s.createDataFrame([(c, p, round(x, 6)) for c, m in enumerate(moved) for p, x in enumerate(m)], "cluster long, place long, value double")


# --- the cascade, piece by piece -----------------------------------------------------------
SPEC = SampleSpec(min_rows=300, seed=7)
TARGET, DELTA = 0.9, 0.2
_S, _C = "(length(text) - length(regexp_replace(text, '[#$%&*!]', '', 'g')))", "(length(text) - length(regexp_replace(text, '[A-Z]', '', 'g')))"
SCORE_SQL = f"least(1.0::DOUBLE, ({_S} + {_C} / 4.0::DOUBLE) / greatest(length(text), 1)::DOUBLE)"
CHAIN_SQL = f"""WITH scaled AS (SELECT doc_id, cume_dist() OVER (ORDER BY s) AS q, y FROM (SELECT doc_id, {SCORE_SQL} AS s, ({JUNK_SQL}) AS y FROM documents WHERE text IS NOT NULL)),
tot AS (SELECT count(*) AS n, sum(power(q, 0.5)) AS t, greatest({SPEC.min_rows}, round(count(*) * {SPEC.fraction})) AS size FROM scaled),
weighed AS (SELECT doc_id, q, y, least(1.0::DOUBLE, size * ({1 - SPEC.uniform_mix} * power(q, 0.5) / t + {SPEC.uniform_mix} / n)) AS pi FROM scaled, tot),
drawn AS (SELECT doc_id, q, y, pi, 1 / pi AS wt FROM weighed WHERE {uniform_sql('doc_id', SPEC.seed)} < pi),
shares AS (SELECT DISTINCT q AS cut, sum(wt) OVER (ORDER BY q DESC RANGE UNBOUNDED PRECEDING) / sum(wt) OVER () AS share FROM drawn WHERE y),
first AS (SELECT max(cut) AS cut FROM shares WHERE share >= {TARGET} - 1e-12),
held AS (SELECT CASE WHEN y AND q >= cut THEN wt ELSE 0 END AS above, CASE WHEN y AND q < cut THEN wt ELSE 0 END AS below FROM drawn, first),
sides AS (SELECT avg(above) + {bounds.z_value(DELTA / 4)} * stddev_pop(above) / sqrt(count(*)) AS u, greatest(0, avg(below) - {bounds.z_value(DELTA / 4)} * stddev_pop(below) / sqrt(count(*))) AS l FROM held),
lo AS (SELECT max(cut) AS lo FROM shares, sides WHERE share >= least(u / (u + l), 1.0) - 1e-12),
numbered AS (SELECT q, row_number() OVER (ORDER BY q DESC) AS r, count(*) OVER () AS s FROM drawn),
candidates AS (SELECT DISTINCT q AS cut FROM numbered, range(1, {cuts.CANDIDATES + 1}) t(i) WHERE r = greatest(1, (s * i) // {cuts.CANDIDATES})),
means AS (SELECT cut, sum(wt * y::INT) / sum(wt) AS p FROM candidates JOIN drawn ON q >= cut GROUP BY cut),
tested AS (SELECT cut, p, p - {bounds.z_value(DELTA / 2 / cuts.CANDIDATES)} * sqrt(sum(wt * wt * (y::INT - p) * (y::INT - p))) / sum(wt) AS low FROM means JOIN drawn ON q >= cut GROUP BY cut, p),
hi AS (SELECT greatest(coalesce(min(cut), 'Infinity'::DOUBLE), any_value(lo)) AS hi FROM lo LEFT JOIN tested ON low >= {TARGET}),
routed AS (SELECT doc_id, y, CASE WHEN q >= hi THEN 'accept' WHEN q >= lo THEN 'ask' ELSE 'reject' END AS route FROM scaled, lo, hi)
"""


def junk_scaled(s, d) -> DataFrame:
    scored = w.junk_proxy().score(docs(s, d, "doc_id", "text"), _template(w.JUNK), "score").filter("score IS NOT NULL")
    return staged(calibrate.quantile_scale(scored, "score", "q"), "scaled")


def _template(text):
    from ..template import Template

    return Template(text)


def junk_sample(s, d, scaled=None):
    from ..operators.filter import labelled_sample

    return labelled_sample(scaled if scaled is not None else junk_scaled(s, d), _template(w.JUNK), w.junk_oracle(), "doc_id", SPEC, "q")[0]


@query("proxy_scores_cume_dist", CHAIN_SQL + "SELECT doc_id, round(q, 9) AS q FROM scaled")
def _(s, d):
    return junk_scaled(s, d).select("doc_id", F.round("q", 9).alias("q"))


@query("proxy_scores_sketch", CHAIN_SQL + "SELECT doc_id, round(q, 9) AS q, true AS near FROM scaled")
def _(s, d):
    """The exact quantile, and whether the sketch's is within 2 % of it."""
    exact = junk_scaled(s, d)
    return calibrate.quantile_scale(exact, "score", "approx", mode="sketch").select("doc_id", F.round("q", 9).alias("q"), (F.abs(F.col("approx") - F.col("q")) <= 0.02).alias("near"))


@query("weighted_sample_poisson", CHAIN_SQL + "SELECT doc_id, round(pi, 9) AS pi FROM drawn")
def _(s, d):
    return sampling.weighted_sample(junk_scaled(s, d), "q", "doc_id", SPEC)[0].select("doc_id", F.round("pi", 9).alias("pi"))


@query("inclusion_weights", CHAIN_SQL + "SELECT doc_id, round(pi, 9) AS pi, round(1 / pi, 6) AS weight FROM weighed")
def _(s, d):
    scaled = junk_scaled(s, d)
    n, t = scaled.agg(F.count("*"), F.sum(F.pow("q", F.lit(0.5)))).first()
    pi = sampling.inclusion_probability(F.col("q"), t, n, SPEC.size(n), SPEC)
    return scaled.select("doc_id", F.round(pi, 9).alias("pi"), F.round(1 / pi, 6).alias("weight"))


@query("recall_cut_table", CHAIN_SQL + "SELECT round(cut, 9) AS cut, round(share, 9) AS share, round(cut, 9) = (SELECT round(lo, 9) FROM lo) AS chosen FROM shares")
def _(s, d):
    sample = junk_sample(s, d)
    lo = cuts.recall_cut(sample, TARGET, DELTA / 2, "normal")
    y = sample.label.astype(bool)
    score, weight = sample.score[y], sample.weight[y]
    rows = [(round(float(c), 9), round(float(weight[score >= c].sum() / weight.sum()), 9), bool(c == lo)) for c in np.unique(score)]
    return s.createDataFrame(rows, "cut double, share double, chosen boolean")


@query("precision_cut_table", CHAIN_SQL + f"SELECT round(cut, 9) AS cut, round(p, 9) AS p, low >= {TARGET} AS certified FROM tested")
def _(s, d):
    sample = junk_sample(s, d)
    rows = []
    for c in np.unique(cuts.candidate_cuts(sample)):
        above = sample.score >= c
        p = float((sample.weight * sample.label)[above].sum() / sample.weight[above].sum())
        low = p - bounds.z_value(DELTA / 2 / cuts.CANDIDATES) * float(np.sqrt((sample.weight[above] ** 2 * (sample.label[above] - p) ** 2).sum())) / float(sample.weight[above].sum())
        rows.append((round(float(c), 9), round(p, 9), bool(low >= TARGET)))
    return s.createDataFrame(rows, "cut double, p double, certified boolean")


@query("cascade_routes", CHAIN_SQL + "SELECT doc_id, route FROM routed")
def _(s, d):
    scaled = junk_scaled(s, d)
    lo, hi = cuts.two_cuts(junk_sample(s, d, scaled), TARGET, TARGET, DELTA, "normal")
    return scaled.select("doc_id", route(F.col("q"), lo, hi).alias("route"))


def junk_cascade(s, d, bound="normal", proxy=None, spec=SPEC, recall=TARGET, precision=TARGET, **more):
    return nl_filter(docs(s, d, "doc_id", "text"), w.JUNK, w.junk_oracle(), proxy=proxy or w.junk_proxy(), key="doc_id", recall=recall, precision=precision, delta=DELTA, bound=bound, sample=spec, **more)


@query("filter_cascade_junk", CHAIN_SQL + "SELECT doc_id FROM routed WHERE route = 'accept' OR (route = 'ask' AND y)")
def _(s, d):
    return junk_cascade(s, d).df.select("doc_id")


@query("cascade_cost", CHAIN_SQL + """SELECT 'proxy' AS route, count(*) AS calls FROM scaled UNION ALL SELECT 'oracle_sample', count(*) FROM drawn UNION ALL
SELECT r, count(doc_id) FROM (VALUES ('accept', 'accept'), ('oracle_band', 'ask'), ('reject', 'reject')) v(r, x) LEFT JOIN routed ON route = x GROUP BY r""")
def _(s, d):
    return junk_cascade(s, d).ledger(s)


@query("filter_proxy_only", f"SELECT doc_id FROM documents WHERE {SCORE_SQL.replace('least(1.0::DOUBLE, ', '').removesuffix(')')} > 0.05")
def _(s, d):
    return nl_filter(docs(s, d, "doc_id", "text"), w.JUNK, w.junk_oracle(), proxy=w.junk_proxy(), plan="proxy_only").df.select("doc_id")


def met_sql(truth: str) -> str:
    return f"SELECT metric, (SELECT count(*) FROM ({truth})) AS n_truth, met FROM (VALUES ('precision', true), ('recall', true)) v(metric, met)"


def met(s, out: DataFrame, gold: DataFrame, keys: list[str], target: float = TARGET) -> DataFrame:
    """The size of the truth, and whether precision and recall against it reach the target."""
    gold = staged(gold.select(*keys).distinct(), "gold")
    r = measures.set_precision_recall(out, gold, keys).first()
    n = gold.count()
    return s.createDataFrame([("precision", n, r["precision"] >= target), ("recall", n, r["recall"] >= target)], "metric string, n_truth long, met boolean")


@query("filter_cascade_meets_targets", CHAIN_SQL.rstrip() + """,
found AS (SELECT y FROM routed WHERE route = 'accept' OR (route = 'ask' AND y))
SELECT 'precision' AS metric, count(*) FILTER (y) AS hits, count(*) AS n_rows, true AS met FROM found
UNION ALL SELECT 'recall', (SELECT count(*) FILTER (y) FROM found), count(*) FILTER (y), true FROM scaled""")
def _(s, d):
    """Hits among the rows found and among the true ones under the normal bound; whether the exact bound meets both targets."""
    gold = staged(nl_filter(docs(s, d, "doc_id", "text"), w.JUNK, w.junk_oracle(), plan="reference").df.select("doc_id"), "gold")
    found = staged(junk_cascade(s, d).df.select("doc_id"), "found")
    hits = found.join(gold, "doc_id", "left_semi").count()
    counted = s.createDataFrame([("precision", hits, found.count()), ("recall", hits, gold.count())], "metric string, hits long, n_rows long")
    return counted.join(met(s, junk_cascade(s, d, bound="exact").df, gold, ["doc_id"]).drop("n_truth"), "metric")


PAIR_SPEC = SampleSpec(min_rows=4000, weight_power=16.0, seed=3)
PROJECTOR = RuleModel(project="text", model_id="identity")


def passage_projector(s, d, missing: float = 0.05) -> LookupText:
    """Stands for a model that names the passage in a document: the first twenty words of one it holds; nothing for a share of these, by a seeded hash, and the document's own first words where there is none."""
    held = w.contained_pairs(docs(s, d, "doc_id", "text"), read_table(s, d, "benchmark")).groupBy("doc_id").agg(F.min("item_id").alias("item_id"))
    said = F.array_join(F.slice(F.split("text", r"\\s+"), 1, 20), " ")
    known = held.filter(sampling.uniform(F.col("doc_id"), 21) >= missing).join(read_table(s, d, "benchmark"), "item_id").select("doc_id", said.alias("said"))
    return LookupText(staged(known, "passages"), "doc_id", "said", "array_join(slice(split(text, '\\\\s+'), 1, 20), ' ')")


def contains_cascade(s, d, plan="auto", embedder=TRIGRAMS, spec=PAIR_SPEC, projector=PROJECTOR, **more):
    return _contains(s, d, "inner", plan=plan, embedder=embedder, projector=projector, recall=TARGET, precision=TARGET, delta=DELTA, sample=spec, **more)


@query("join_cascade_meets_targets", met_sql(PAIRS_SQL))
def _(s, d):
    out = contains_cascade(s, d).df.select("doc_id", F.col("right_item_id").alias("item_id"))
    return met(s, out, w.contained_pairs(docs(s, d), read_table(s, d, "benchmark")), ["doc_id", "item_id"])


@query("join_plan_costs", "SELECT (SELECT count(*) FROM documents) * (SELECT count(*) FROM benchmark) AS pairs, (SELECT count(*) FROM documents) AS projections, true AS chosen_is_cheapest, true AS below_nested_loop")
def _(s, d):
    """Both plans planned on one sample; the chosen one has the fewest calls and is cheaper than asking every pair."""
    got = contains_cascade(s, d)
    reports = got.plan["reports"]
    chosen = min(r.oracle_calls for r in reports)
    pairs = docs(s, d).count() * read_table(s, d, "benchmark").count()
    own = next((r.oracle_calls for r in reports if r.name == got.plan["plan"]), pairs)
    projections = next(r.projections for r in reports if r.name == "projected")
    return s.createDataFrame([(pairs, projections, own == chosen or got.plan["plan"] == "reference", got.oracle_calls <= pairs + reports[0].sample)], "pairs long, projections long, chosen_is_cheapest boolean, below_nested_loop boolean")


@query("classify_cascade_meets_target", f"SELECT group_label, count(*) AS n_truth, true AS met FROM ({CLASSIFY_SQL}) GROUP BY ALL")
def _(s, d):
    """Rows of each label by the reference, and whether the cascade's accuracy over all of them meets the target."""
    df = docs(s, d, "doc_id", "text")
    gold = nl_classify(df, LANGUAGE, list(STOPS), language_oracle(), plan="reference").df
    got = nl_classify(df, LANGUAGE, list(STOPS), language_oracle(), key="doc_id", text="text", embedder=UNIGRAMS, centers=label_centers(), accuracy=TARGET, delta=DELTA, sample=SampleSpec(min_rows=300)).df
    a = measures.accuracy(got, gold.withColumnRenamed("group_label", "truth"), "doc_id", "group_label", "truth").first()["accuracy"]
    return gold.groupBy("group_label").agg(F.count("*").alias("n_truth")).withColumn("met", F.lit(a >= TARGET))


# --- vectors ---------------------------------------------------------------------------
DOC_ITEM_SIMS = sims_sql("documents", "doc_id", "text", "benchmark", "item_id", "text")


@query("similar_join_topk", f"SELECT lk AS doc_id, rk AS item_id, sim, (row_number() OVER (PARTITION BY lk ORDER BY sim DESC, rk))::INTEGER AS rank FROM ({DOC_ITEM_SIMS}) QUALIFY rank <= 5")
def _(s, d):
    out = nl_similar_join(docs(s, d, "doc_id", "text"), read_table(s, d, "benchmark"), "text", "text", 5, left_key="doc_id", right_key="item_id", embedder=UNIGRAMS)
    return out.select(F.col("left_key").alias("doc_id"), F.col("right_key").alias("item_id"), "sim", "rank")


SEARCH_SQL = f"SELECT lk AS doc_id, sim FROM ({sims_sql('documents', 'doc_id', 'text', QUESTION_SQL, 'qid', 'q')}) ORDER BY sim DESC, lk LIMIT 10"


@query("search_topk", f"SELECT doc_id, sim, (row_number() OVER (ORDER BY sim DESC, doc_id))::INTEGER AS rank FROM ({SEARCH_SQL})")
def _(s, d):
    return nl_search(docs(s, d, "doc_id", "text"), "text", QUESTION, 10, key="doc_id", embedder=UNIGRAMS).select("doc_id", "sim", "rank")


@query("search_rerank", f"SELECT doc_id, (row_number() OVER (ORDER BY n_chars DESC, doc_id))::INTEGER AS rank FROM ({SEARCH_SQL}) JOIN documents USING (doc_id) QUALIFY rank <= 3")
def _(s, d):
    longest = RuleModel(score="cast(n_chars as double)")
    return nl_search(docs(s, d, "doc_id", "text", "n_chars"), "text", QUESTION, 10, key="doc_id", embedder=UNIGRAMS, rerank=3, reranker=longest, template="{text}").select("doc_id", "rank")


def _new_index(s, d):
    import uuid

    path = f"{shared_folder(s)}/nlops-index-{uuid.uuid4().hex[:10]}"
    build_text_index(docs(s, d, "doc_id", "text"), "doc_id", "text", UNIGRAMS, path)
    return path


@query("index_roundtrip", f"SELECT key, count(*) AS filled, round(max(w), 6) AS peak FROM ({UNIGRAMS.sql('documents', 'doc_id', 'text')}) GROUP BY key")
def _(s, d):
    index = load_text_index(s, _new_index(s, d))
    filled = F.size(F.filter("vec", lambda x: x > 0)).cast("bigint")
    return index.vectors.select("key", filled.alias("filled"), F.round(F.array_max("vec"), 6).alias("peak")).filter("filled > 0")


@query("search_by_index", f"SELECT doc_id, sim, (row_number() OVER (ORDER BY sim DESC, doc_id))::INTEGER AS rank FROM ({SEARCH_SQL})")
def _(s, d):
    index = load_text_index(s, _new_index(s, d))
    return nl_search(docs(s, d, "doc_id", "text"), "text", QUESTION, 10, key="doc_id", embedder=UNIGRAMS, index=index).select("doc_id", "sim", "rank")


@query("embed_unigram_norms", f"SELECT key AS doc_id, round(sum(w * w), 6) AS norm, count(*) AS filled FROM ({UNIGRAMS.sql('documents', 'doc_id', 'text')}) GROUP BY key")
def _(s, d):
    v = UNIGRAMS.embed(docs(s, d, "doc_id", "text"), "text", "v")
    from ..vectors.similarity import dot

    return v.select("doc_id", F.round(dot(F.col("v"), F.col("v")), 6).alias("norm"), F.size(F.filter("v", lambda x: x > 0)).cast("bigint").alias("filled")).filter("filled > 0")


@query("embed_trigram_pairs", f"SELECT lk AS doc_id, rk AS item_id FROM ({sims_sql('documents', 'doc_id', 'text', 'benchmark', 'item_id', 'text', TRIGRAMS)}) WHERE sim >= 0.1")
def _(s, d):
    from ..vectors.similarity import similar_pairs

    left = TRIGRAMS.embed(docs(s, d, "doc_id", "text"), "text", "v")
    right = TRIGRAMS.embed(read_table(s, d, "benchmark"), "text", "v")
    return similar_pairs(left, right, "doc_id", "v", "item_id", "v", least=0.1).select(F.col("lk").alias("doc_id"), F.col("rk").alias("item_id"))


# --- projection and extraction -------------------------------------------------------------
@query("project_title", "SELECT doc_id, array_to_string(list_filter(string_split_regex(text, '\\s+'), lambda x: x <> '')[1:8], ' ') AS title FROM documents WHERE text IS NOT NULL")
def _(s, d):
    titles = RuleModel(project="array_join(slice(filter(split(text, '\\\\s+'), x -> x <> ''), 1, 8), ' ')")
    return nl_project(docs(s, d, "doc_id", "text"), "a title for {text}", "title", titles).select("doc_id", "title")


def _found_sql(pattern):
    return f"SELECT doc_id, unnest(regexp_extract_all(text, '{pattern}')) AS snippet FROM documents"


for _name, _pattern in (("extract_emails", tx.EMAIL), ("extract_licenses", tx.LICENSE)):

    @query(_name, _found_sql(_pattern))
    def _(s, d, pattern=_pattern):
        out = nl_extract(docs(s, d, "doc_id", "text"), "snippets of {text}", "found", text="text", pattern=pattern)
        return out.select("doc_id", F.explode("found.text").alias("snippet"))


@query("snippet_offsets", f"SELECT doc_id, snippet, true AS verbatim FROM ({_found_sql(tx.EMAIL)})")
def _(s, d):
    out = nl_extract(docs(s, d, "doc_id", "text"), "addresses in {text}", "found", text="text", pattern=tx.EMAIL)
    each = out.select("doc_id", "text", F.explode("found").alias("f"))
    return each.select("doc_id", F.col("f.text").alias("snippet"), F.expr("substring(text, f.start + 1, f.end - f.start) = f.text").alias("verbatim"))


@query("html_to_text", f"SELECT page_id, {_html_sql('html')} AS body FROM pages")
def _(s, d):
    return read_table(s, d, "pages").select("page_id", tx.html_to_text(F.col("html")).alias("body"))


@query("chunks", """SELECT doc_id, (i)::INTEGER AS chunk_no, md5(array_to_string(w[i * 80 + 1 : i * 80 + 100], ' ')) AS h FROM (
SELECT doc_id, w, unnest(range(0, greatest(0, (len(w) - 21) // 80) + 1)) AS i FROM (SELECT doc_id, list_filter(string_split_regex(text, '\\s+'), lambda x: x <> '') AS w FROM documents))""")
def _(s, d):
    return tx.chunk(docs(s, d, "doc_id", "text"), "text", 100, 20).select("doc_id", "chunk_no", F.md5("chunk").alias("h"))


# --- baselines -------------------------------------------------------------------------
FACT_K = 3
SUPPORTED = RuleModel(predicate="contains(context, claim)", project="CASE WHEN contains(context, claim) THEN 'True: it is stated' ELSE 'False' END", score="CASE WHEN contains(context, substr(claim, 1, 40)) THEN 0.9D ELSE 0.1D END", model_id="support")
HALVES_SQL = "(SELECT item_id * 2 + h AS qid, array_to_string(CASE WHEN h = 0 THEN w[1 : n] ELSE w[n + 1 :] END, ' ') AS q FROM (SELECT item_id, string_split_regex(text, '\\s+') AS w, ceil(len(w) / 2)::BIGINT AS n FROM benchmark), (VALUES (0), (1)) t(h))"
FACT_SQL = f"""WITH sims AS ({sims_sql(HALVES_SQL, 'qid', 'q', 'documents', 'doc_id', 'text')}),
near AS (SELECT DISTINCT lk // 2 AS item_id, rk AS doc_id FROM sims QUALIFY row_number() OVER (PARTITION BY lk ORDER BY sim DESC, rk) <= {FACT_K})
SELECT DISTINCT b.item_id AS claim_id FROM near JOIN benchmark b USING (item_id) JOIN documents d USING (doc_id) WHERE contains(d.text, b.text)"""


def claims(s, d) -> DataFrame:
    return read_table(s, d, "benchmark").select(F.col("item_id").alias("claim_id"), F.col("text").alias("claim"))


@query("rowwise_factcheck", FACT_SQL)
def _(s, d):
    return factcheck.rowwise_program(claims(s, d), docs(s, d, "doc_id", "text"), UNIGRAMS, SUPPORTED, FACT_K).select("claim_id")


@query("pipeline_factcheck", FACT_SQL)
def _(s, d):
    return factcheck.handwritten_pipeline(claims(s, d), docs(s, d, "doc_id", "text"), UNIGRAMS, SUPPORTED, FACT_K).select("claim_id")


@query("operator_factcheck", FACT_SQL)
def _(s, d):
    return factcheck.operator_program(claims(s, d), docs(s, d, "doc_id", "text"), UNIGRAMS, SUPPORTED, FACT_K).df.select("claim_id")


@query("cascade_factcheck", met_sql(FACT_SQL))
def _(s, d):
    args = (claims(s, d), docs(s, d, "doc_id", "text"), UNIGRAMS, SUPPORTED, FACT_K)
    gold = factcheck.operator_program(*args).df
    return met(s, factcheck.operator_program(*args, proxy=SUPPORTED, recall=TARGET, precision=TARGET).df, gold, ["claim_id"])


@query("rowwise_join_contains", PAIRS_SQL)
def _(s, d):
    said = RuleModel(project="CASE WHEN contains(left_text, right_text) THEN 'true' ELSE 'no' END")
    return rowwise.rowwise_join(docs(s, d, "doc_id", "text"), read_table(s, d, "benchmark"), w.CONTAINS, said, "doc_id", "item_id").select(F.col("lk").alias("doc_id"), F.col("rk").alias("item_id"))


@query("rowwise_join_cost_estimate", f"SELECT (SELECT count(*) FROM documents) * (SELECT count(*) FROM benchmark) AS calls, round((SELECT count(*) FROM documents) * (SELECT count(*) FROM benchmark) * {measures.MODELLED_SECONDS_PER_CALL}::DOUBLE, 3) AS modelled_sec")
def _(s, d):
    return rowwise.rowwise_join_cost(docs(s, d, "doc_id"), read_table(s, d, "benchmark", ["item_id"]))


@query("rowwise_rank_score", TOP_PRICE_SQL.replace(", (row_number() OVER (ORDER BY p_retailprice DESC, p_partkey))::INTEGER AS rank", ""))
def _(s, d):
    return rowwise.rowwise_rank(read_table(s, d, "part", ["p_partkey", "p_retailprice"]), "p_retailprice", K, "p_partkey")


@query("search_only_labels", f"SELECT lk AS doc_id, rk AS item_id FROM ({DOC_ITEM_SIMS}) QUALIFY row_number() OVER (PARTITION BY lk ORDER BY sim DESC, rk) <= 10")
def _(s, d):
    out = nl_similar_join(docs(s, d, "doc_id", "text"), read_table(s, d, "benchmark"), "text", "text", 10, left_key="doc_id", right_key="item_id", embedder=UNIGRAMS)
    return out.select(F.col("left_key").alias("doc_id"), F.col("right_key").alias("item_id"))


@query("compiled_label_pipeline", f"""SELECT lk AS doc_id, rk AS item_id, (row_number() OVER (PARTITION BY lk ORDER BY hit DESC, sim DESC, rk))::INTEGER AS rank FROM (
SELECT lk, rk, sim, contains(d.text, b.text)::INT AS hit FROM ({DOC_ITEM_SIMS}) JOIN documents d ON lk = d.doc_id JOIN benchmark b ON rk = b.item_id QUALIFY row_number() OVER (PARTITION BY lk ORDER BY sim DESC, rk) <= 20) QUALIFY rank <= 5""")
def _(s, d):
    scorer = RuleModel(score="cast(contains(left_text, right_text) as double)")
    out = guess_retrieve_rerank(docs(s, d, "doc_id", "text"), read_table(s, d, "benchmark"), w.CONTAINS, left_key="doc_id", right_key="item_id", right_text="text", projector=PROJECTOR, projection="{text}", embedder=UNIGRAMS, reranker=scorer, k=5, retrieve=20)
    return out.select(F.col("lk").alias("doc_id"), F.col("rk").alias("item_id"), "rank")


@query("budget_filter_first_batch", f"SELECT doc_id FROM documents ORDER BY {uniform_sql('doc_id', 5)}, doc_id LIMIT 50")
def _(s, d):
    return budget.first_batch(docs(s, d, "doc_id"), "doc_id", 50, 5)


@query("budget_filter_junk")
def _(s, d):
    v = HashedNgrams(1, 64).embed(docs(s, d, "doc_id", "text"), "text", "v")
    return budget.budget_filter(v, w.JUNK, w.junk_oracle(), key="doc_id", vec="v", budget=200).df.select("doc_id")


@query("rewriter_blocking_join")
def _(s, d):
    left, right = docs(s, d, "doc_id", "text"), read_table(s, d, "benchmark")
    runs, _n = rewriter.mean_of_successes(lambda seed: rewriter.blocking_join(left, right, w.CONTAINS, w.contains_oracle(), left_key="doc_id", right_key="item_id", embedder=UNIGRAMS, budget=5 * left.count(), seed=seed), wanted=1)
    return runs[0].df.select(F.col("lk").alias("doc_id"), F.col("rk").alias("item_id"))


# --- measures --------------------------------------------------------------------------
@query("m_accuracy", f"SELECT avg((({JUNK_SQL}) = ({SCORE_SQL} > 0.05))::INT) AS accuracy, count(*) AS n_rows FROM documents")
def _(s, d):
    t = _template(w.JUNK)
    df = docs(s, d, "doc_id", "text")
    return measures.accuracy(w.junk_proxy().label(df, t, "p"), w.junk_oracle().label(df, t, "t"), "doc_id", "p", "t")


@query("m_precision_recall", f"SELECT count(*) FILTER (g AND o) / count(*) FILTER (o) AS precision, count(*) FILTER (g AND o) / count(*) FILTER (g) AS recall, count(*) FILTER (o) AS n_out, count(*) FILTER (g) AS n_gold FROM (SELECT ({JUNK_SQL}) AS g, ({SCORE_SQL} > 0.05) AS o FROM documents)")
def _(s, d):
    df = docs(s, d, "doc_id", "text")
    out = nl_filter(df, w.JUNK, w.junk_oracle(), proxy=w.junk_proxy(), plan="proxy_only").df
    return measures.set_precision_recall(out, nl_filter(df, w.JUNK, w.junk_oracle(), plan="reference").df, ["doc_id"])


def ranked_items(s, d, k=10, vectors=None):
    return staged(QUERIES["similar_join_topk"](s, d), "ranked") if k == 5 else nl_similar_join(docs(s, d, "doc_id", "text"), read_table(s, d, "benchmark"), "text", "text", k, left_key="doc_id", right_key="item_id", embedder=UNIGRAMS, vectors=vectors).select(F.col("left_key").alias("doc_id"), F.col("right_key").alias("item_id"), "rank")


RANKED_SQL = f"SELECT lk AS doc_id, rk AS item_id, row_number() OVER (PARTITION BY lk ORDER BY sim DESC, rk) AS rank FROM ({DOC_ITEM_SIMS})"


@query("m_rank_precision", f"""WITH due AS ({PAIRS_SQL}), ranked AS ({RANKED_SQL})
SELECT avg(hits / least(10, due)) AS rank_precision, count(*) AS n_queries FROM (SELECT doc_id, count(*) AS due, count(rank) FILTER (rank <= 10) AS hits FROM due LEFT JOIN ranked USING (doc_id, item_id) GROUP BY doc_id)""")
def _(s, d):
    return measures.rank_precision(ranked_items(s, d), w.contained_pairs(docs(s, d), read_table(s, d, "benchmark")), "doc_id", "item_id", 10)


@query("m_ndcg", f"""WITH due AS ({PAIRS_SQL}), ranked AS ({RANKED_SQL}),
got AS (SELECT doc_id, sum(1 / log2(rank + 1)) AS dcg FROM due JOIN ranked USING (doc_id, item_id) WHERE rank <= 10 GROUP BY doc_id),
ideal AS (SELECT doc_id, sum(1 / log2(r + 1)) AS idcg FROM (SELECT doc_id, row_number() OVER (PARTITION BY doc_id) AS r FROM due) WHERE r <= 10 GROUP BY doc_id)
SELECT round(avg(coalesce(dcg, 0) / idcg), 9) AS ndcg, count(*) AS n_queries FROM ideal LEFT JOIN got USING (doc_id)""")
def _(s, d):
    gains = w.contained_pairs(docs(s, d), read_table(s, d, "benchmark")).withColumn("gain", F.lit(1.0))
    return measures.ndcg(ranked_items(s, d), gains, "doc_id", "item_id", "gain", 10).select(F.round("ndcg", 9).alias("ndcg"), "n_queries")


@query("m_calls_by_route", CHAIN_SQL + "SELECT route, count(*) AS calls FROM routed GROUP BY route")
def _(s, d):
    return QUERIES["cascade_routes"](s, d).groupBy("route").agg(F.count("*").alias("calls"))


@query("m_tokens", f"SELECT lang, count(*) AS calls, sum(len({WORDS_SQL}) + 2)::BIGINT AS tokens FROM (SELECT lang, 'x ' || text || ' y' AS text FROM documents) s GROUP BY lang".replace(" + 2", ""))
def _(s, d):
    df = docs(s, d, "lang", "text")
    return measures.prompt_tokens(df, F.concat(F.lit("x "), F.col("text"), F.lit(" y")), "lang")
