"""The experiment workloads on the given tables."""

from __future__ import annotations

from dataclasses import replace
from functools import reduce

from pyspark.sql import DataFrame, Window as W, functions as F

from cutseg.functions import units
from cutseg.operators import affinity as A, graph as G, laplacian as L, metrics as M, segment as S
from cutseg.operators.corpus import fit_model
from cutseg.plans.methods import CUTS, PRINTED_CUTS, _curve, _part_bands, predictions, query, r6, _round_scores
from cutseg.plans.twins import sql
from cutseg.sources import tables


def _named(df: DataFrame, **names) -> DataFrame:
    return df.select(*[F.lit(v).alias(k) for k, v in names.items()], "*")


def _union(frames: list[DataFrame]) -> DataFrame:
    return reduce(lambda a, b: a.unionByName(b), frames)


def grid(x, methods, sents: DataFrame | None = None) -> DataFrame:
    """Scores of methods on the same sentences."""
    truth = M.gold(x.test if sents is None else sents)
    return _round_scores(_union([_named(M.score_words(predictions(x, m, sents), truth), method=m) for m in methods]))


@query("x1_domain_cuts")
def _x1(x) -> DataFrame:
    """The domain method over cuts: words a sentence, and F against spacing."""
    truth, out = M.gold(x.dev), []
    for cut in CUTS:
        words = S.segment(x.dev, x.model, replace(S.DOMAIN_SCALE, cut=cut), sets=x.sets)
        stats = M.granularity_stats(words).select("lang", r6("words_per_sentence", "words_per_sentence"), r6("mean_len", "mean_len"))
        out.append(_named(M.score_words(words, truth).join(stats, "lang"), cut=cut))
    return _round_scores(_union(out))


@query("x2_granularity_bench")
def _x2(x) -> DataFrame:
    """Number of words over cuts for benchmark sentences, by inertia alone."""
    bands = A.to_bands(x.benchmark, A.adjacent_weights(x.benchmark, x.model), A.skip_weights(x.benchmark, x.model))
    return _curve(bands, "plain", CUTS)


@query("x3_part_terms")
def _x3(x) -> DataFrame:
    """Recovery of the closed toy language's tokens from its despaced names."""
    words = S.segment(x.part_names, x.part_model, replace(S.DOMAIN, k=2, cluster="contiguous"))
    return _round_scores(M.score_words(words, M.gold(x.part_names)))


query("x4_x5_dictionaries")(lambda x: grid(x, ["lexicon", "lexicon_dev", "lexicon_in_place", "trained", "trained_dev", "trained_in_place"]))
query("x5_benchmark")(lambda x: grid(x, ["lexicon_dev", "trained_dev", "trained_in_place", "likelihood"], x.benchmark))
query("x7_weakening")(lambda x: grid(x, ["domain_no_sets", "domain_soft", "domain_hard", "domain", "domain_scale"]))
query("x1_printed_cuts")(lambda x: grid(x, [f"domain_{c}" for c in PRINTED_CUTS]))
query("x9_forms")(lambda x: grid(x, ["domain", "domain_sym", "domain_no_skip"]))
query("x12_x13_baselines")(lambda x: grid(x, ["domain_scale", "trained_in_place", "entropy", "entropy_rise", "likelihood", "longest", "threshold", "chars", "one", "tagger"]))
query("f_gain")(lambda x: M.compare(grid(x, ["lexicon_dev", "trained_dev"]), "lexicon_dev").select("method", "lang", "f1", r6("f_gain", "f_gain")))


@query("x8_templates")
def _x8(x) -> DataFrame:
    """F of sentences that occur once and of repeated ones."""
    times = x.test.groupBy("lang", "s").agg(F.count("*").alias("times"))
    truth = x.test.join(times, ["lang", "s"]).withColumn("words", units.gold_words(F.col("raw"))).withColumn("repeated", F.col("times") > 1)
    return _round_scores(M.score_words(predictions(x, "domain_scale"), truth.select("sent_id", "lang", "repeated", "s", "words"), by=("lang", "repeated")))


query("x10_components", sql("""select n_components, count(*) as n from (select t.sent_id, 1 + coalesce(sum((e.w = 0)::int), 0)::bigint as n_components from test t left join edges e using (sent_id) group by t.sent_id) group by all""", "test", "edges"))(
    lambda x: L.components(
        A.to_bands(x.test, A.adjacent_weights(x.test, x.model), A.skip_weights(x.test, x.model))).groupBy(F.col("n_components").cast("long").alias("n_components")).agg(F.count("*").alias("n")))


@query("x14_quality_slices")
def _x14(x) -> DataFrame:
    labels = x.table("labels").select("doc_id", "quality", "toxic")
    truth = x.test.join(labels, "doc_id").withColumn("words", units.gold_words(F.col("raw")))
    return _round_scores(M.score_words(predictions(x, "domain_scale"), truth.select("sent_id", "lang", "quality", "toxic", "s", "words"), by=("lang", "quality", "toxic")))


@query("x15_chat_shift")
def _x15(x) -> DataFrame:
    """Chat segmented with the document model and with a model of other chats."""
    own = fit_model(x.conversations.where("conv_id % 2 = 0"))
    odd = x.conversations.where("conv_id % 2 = 1")
    cfg = replace(S.DOMAIN_SCALE, cut=0.3)
    truth = M.gold(odd)
    return _round_scores(_union([_named(M.score_words(S.segment(odd, m, cfg), truth), model=name) for name, m in (("documents", x.model), ("chat", own))]))


@query("x16_web")
def _x16(x) -> DataFrame:
    pages = tables.page_texts(x.table("pages")).withColumn("lang", F.coalesce(F.nullif(F.regexp_extract("url", "/(en|fr|de|es)/", 1), F.lit("")), F.lit("en")))
    sents = units.sentences(pages, id_col="page_id", keep=("lang",))
    return S.segment(sents, x.model, replace(S.DOMAIN_SCALE, cut=0.3)).select("sent_id", "lang", F.array_join("words", " ").alias("words"))


query("pages_text", """select page_id, url, trim(regexp_replace(replace(replace(replace(replace(replace(replace(regexp_replace(regexp_replace(regexp_replace(html, '(?is)<script[^>]*>.*?</script>', ' ', 'g'), '(?is)<style[^>]*>.*?</style>', ' ', 'g'), '(?s)<[^>]*>', ' ', 'g'),
  '&lt;', '<'), '&gt;', '>'), '&quot;', '"'), '&#39;', chr(39)), '&nbsp;', ' '), '&amp;', '&'), '\\s+', ' ', 'g')) as text from pages""")(lambda x: tables.page_texts(x.table("pages")))


def _event_symbols(x) -> DataFrame:
    """Sessions of a user (gaps of 12 hours) as sentences over event types."""
    w = W.partitionBy("user_id").orderBy("ts", "event_id")
    us = F.unix_micros(F.col("ts").cast("timestamp"))
    e = x.table("events").withColumn("gap", us - F.lag(us).over(w))
    e = e.withColumn("session", F.sum(F.when(F.coalesce("gap", F.lit(0)) > 12 * 3600 * 1_000_000, 1).otherwise(0)).over(w))
    letter = F.substring("event_type", 1, 1)
    rows = e.groupBy("user_id", "session").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("ts", "event_id", letter.alias("c")))), lambda r: r["c"]), "").alias("s"))
    return rows.select(F.concat_ws(":", "user_id", "session").alias("sent_id"), F.lit("events").alias("lang"), "s", F.length("s").alias("n"))


def _sequence_groups(x, name: str, sents: DataFrame, cut: float) -> DataFrame:
    held = x.ws.table(sents, name)
    return S.segment(held, fit_model(held), replace(S.DOMAIN_SCALE, cut=cut)).select("sent_id", "k", F.array_join("words", " ").alias("words"))


query("x17_event_sequences")(lambda x: _sequence_groups(x, "event-sequences", _event_symbols(x), 0.4))


@query("x18_order_sequences")
def _x18(x) -> DataFrame:
    o = x.table("orders").groupBy("o_custkey").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("o_orderdate", "o_orderkey", F.substring("o_orderpriority", 3, 1).alias("c")))), lambda r: F.lower(r["c"])), "").alias("s"))
    return _sequence_groups(x, "order-sequences", o.select(F.col("o_custkey").cast("string").alias("sent_id"), F.lit("orders").alias("lang"), "s", F.length("s").alias("n")), 0.5)


@query("x19_graph_partition")
def _x19(x) -> DataFrame:
    edges = G.knn_edges(x.table("embeddings"), 8)
    found = G.partition_graph(edges, form="sym", cut=0.3, weakest=0.1)
    return _named(G.agreement(found, x.table("embeddings").select(F.col("vec_id").alias("node"), "label")), form="sym").select("form", r6("purity", "purity"), r6("nmi", "nmi"))


@query("graph_partition")
def _clusters(x) -> DataFrame:
    return G.partition_graph(G.knn_edges(x.table("embeddings"), 8), form="plain", cut=0.5, weakest=0.1)


@query("x20_names_by_nation", sql("""select n.n_name as nation, count(distinct p.p_name) as names, count(*) as lines from lineitem l join part p on p.p_partkey = l.l_partkey join supplier s on s.s_suppkey = l.l_suppkey
  join nation n on n.n_nationkey = s.s_nationkey group by n.n_name""", "part_names"))
def _x20(x) -> DataFrame:
    small = x.table("supplier").join(F.broadcast(x.table("nation")), F.col("s_nationkey") == F.col("n_nationkey")).select("s_suppkey", F.col("n_name").alias("nation"))
    lines = x.table("lineitem").select("l_partkey", "l_suppkey").join(small, F.col("l_suppkey") == F.col("s_suppkey"))
    named = lines.join(x.table("part").select("p_partkey", "p_name"), F.col("l_partkey") == F.col("p_partkey"))
    return named.groupBy("nation").agg(F.countDistinct("p_name").alias("names"), F.count("*").alias("lines"))


@query("part_sweep_monotone")
def _monotone(x) -> DataFrame:
    """Names whose number of words falls as the cut grows: none may."""
    w = W.partitionBy("sent_id").orderBy("cut")
    return _curve(_part_bands(x), "plain", CUTS).withColumn("before", F.lag("k").over(w)).agg(F.count("*").alias("n"), F.sum((F.col("before") > F.col("k")).cast("long")).alias("falls"))
