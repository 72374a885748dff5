"""Queries of the method inventory: statistics, weights, Laplacians, segmenters,
baselines and measures; with DuckDB twins where SQL can express them."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame, functions as F

from cutseg.functions import kernels as K, units
from cutseg.operators import affinity as A, baselines as B, corpus as C, laplacian as L, metrics as M, segment as S
from cutseg.plans.context import context
from cutseg.plans.twins import sql

QUERIES: dict = {}
ORACLE_SQL: dict[str, str] = {}
CUTS = [0.02, 0.05, 0.1, 0.15, 0.3, 1.0, 2.0]


def query(name: str, twin: str | None = None):
    def keep(f):
        QUERIES[name] = lambda spark, sf_dir: f(context(spark, sf_dir))
        if twin:
            ORACLE_SQL[name] = twin
        return f
    return keep


def r6(c, name: str):
    return F.round(c, 6).alias(name)


# --- statistics ---------------------------------------------------------------

query("units_sentences", sql("select sent_id, lang, s, length(s)::bigint as n from all_sents", "all_sents"))(
    lambda x: units.sentences(x.documents).select("sent_id", "lang", "s", F.col("n").cast("long").alias("n")))
query("units_symbols", sql("select lang, c as symbol, count(*) as n from (select lang, unnest(string_split(s, '')) as c from test) group by all", "test"))(
    lambda x: x.test.select("lang", F.explode(units.symbols(F.col("s"))).alias("symbol")).groupBy("lang", "symbol").agg(F.count("*").alias("n")))
query("usable_symbols", sql("select lang, g as symbol, regexp_matches(g, '^\\p{L}$') as usable from uni_g", "uni_g"))(
    lambda x: x.grams[1].select("lang", F.col("g").alias("symbol"), units.is_usable(F.col("g")).alias("usable")))
for n, key, cte in ((1, "ngram_uni", "uni_g"), (2, "ngram_bi", "bi_g"), (3, "ngram_tri", "tri_g")):
    query(key, sql(f"select lang, g, cnt from {cte}", cte))(lambda x, n=n: C.ngram_counts(x.train, n))
query("ngram_all", sql("select * from (select lang, g, cnt from uni_g union all select lang, g, cnt from bi_g union all select lang, g, cnt from tri_g)", "uni_g", "bi_g", "tri_g"))(
    lambda x: C.ngram_tables(x.train)[1].unionByName(C.ngram_tables(x.train)[2]).unionByName(C.ngram_tables(x.train)[3]))
for key, kind, n, col, cte in (("p_next1", "fwd1", 2, "p1", "bi"), ("p_next2", "fwd2", 3, "f2", "tri"), ("p_prev2", "bwd2", 3, "b2", "tri"), ("p_pair", "pair", 3, "pair", "tri")):
    names = "a, b" if n == 2 else "a, b, c"
    query(key, sql(f"select lang, {names}, round({col}, 6) as p from {cte}", cte))(
        lambda x, kind=kind, n=n: C.transitions(x.grams[n], kind).withColumn("p", F.round("p", 6)))
for key, n, cte in (("zcount_bi", 2, "z2"), ("zcount_tri", 3, "z3")):
    query(key, sql(f"select lang, g, round(z, 6) as z from {cte}", cte))(lambda x, n=n: C.standardised_log_counts(x.grams[n]).select("lang", "g", r6("z", "z")))
query("zcount_tokens")(lambda x: C.standardised_log_counts(x.grams[2], over="tokens").select("lang", "g", r6("z", "z")))
query("model_merge", sql("""select lang, g, sum(cnt)::bigint as cnt from (select lang, g, cnt from bi_g union all select lang, substr(s, i, 2) as g, count(*) as cnt
  from (select lang, s, unnest(range(1, length(s))) as i from test) group by all) group by all""", "bi_g", "test"))(
    lambda x: C.merge_counts(x.grams[2], C.ngram_counts(x.test, 2)))
query("train_words", sql("select lang, word, cnt from words", "words"))(lambda x: C.train_words(x.train))
query("ranked_lexicon", sql("select lang, word, rank from lexicon", "lexicon"))(lambda x: C.ranked(x.words))
query("weakening_sets", sql("select lang, ch, set_id from sets", "sets"))(lambda x: C.weakening_sets(x.words, x.grams[1]))

# --- weights ------------------------------------------------------------------


def _summed(edges: DataFrame) -> DataFrame:
    """Edge rows of a sentence as figures that SQL can compare."""
    return edges.groupBy("sent_id").agg(F.count("*").alias("n_edges"), r6(F.sum("w"), "sum_w"), r6(F.max("w"), "max_w"), F.sum((F.col("w") == 0).cast("long")).alias("zeros"))


def _summed_sql(expr: str, source: str) -> str:
    return f"select sent_id, count(*) as n_edges, round(sum({expr}), 6) as sum_w, round(max({expr}), 6) as max_w, sum(({expr} = 0)::int)::bigint as zeros from {source} group by sent_id"


_HARD = "coalesce(list_contains(h2, e.a) or list_contains(h2, e.b), false)"
_SOFT = "coalesce(list_contains(h1, e.a) or list_contains(h1, e.b), false)"
_BY_SET = "left join (select lang, list(ch) filter (set_id = 1) as h1, list(ch) filter (set_id = 2) as h2 from sets group by lang) g using (lang)"
_WEAK = f"e.w / case when {_SOFT} then 4.0 else 1.0 end / case when {_HARD} then 80.0 else 1.0 end"
query("edges_adjacent", sql(_summed_sql("w", "edges"), "edges"))(lambda x: _summed(A.adjacent_weights(x.test, x.model)))
query("edges_skip", sql(_summed_sql("w", "skips"), "skips"))(lambda x: _summed(A.skip_weights(x.test, x.model)))
query("edge_windows", sql("select lang, o, a, b, x, count(*) as n from win group by all", "win"))(lambda x: A.windows(x.test).groupBy("lang", "o", "a", "b", "x").agg(F.count("*").alias("n")))
query("weaken_soft", sql(_summed_sql(f"e.w / case when {_SOFT} then 4.0 else 1.0 end", f"edges e {_BY_SET}"), "edges", "sets"))(
    lambda x: _summed(A.weaken(A.adjacent_weights(x.test, x.model), x.sets, {1: 4.0})))
query("weaken_hard", sql(_summed_sql(f"e.w / case when {_HARD} then 80.0 else 1.0 end", f"edges e {_BY_SET}"), "edges", "sets"))(
    lambda x: _summed(A.weaken(A.adjacent_weights(x.test, x.model), x.sets, {2: 80.0})))
query("weaken_both", sql(_summed_sql(_WEAK, f"edges e {_BY_SET}"), "edges", "sets"))(lambda x: _summed(A.weaken(A.adjacent_weights(x.test, x.model), x.sets)))
_FREE = "select lang, a, b from bi where cnt >= 100"
query("weaken_exceptions", sql(_summed_sql(f"case when f.a is not null then e.w else {_WEAK} end", f"edges e {_BY_SET} left join ({_FREE}) f on f.lang = e.lang and f.a = e.a and f.b = e.b"), "edges", "sets", "bi"))(
    lambda x: _summed(A.weaken(A.adjacent_weights(x.test, x.model), x.sets, except_bigrams=x.model.bi.where("cnt >= 100").select("lang", "a", "b"))))
query("skip_block", sql(_summed_sql("case when coalesce(list_has_any(h2, [e.a, e.b, e.c]), false) then 0 else e.w end", f"skips e {_BY_SET}"), "skips", "sets"))(
    lambda x: _summed(A.block_skip(A.skip_weights(x.test, x.model), x.sets)))
_BOOST = "e.w * case when t.a is not null then 20.0 else 1.0 end"
_IN = lambda t: f"left join {t} t on t.lang = e.lang and t.a = e.a and t.b = e.b"
_ENDS = "left join singles p on p.lang = e.lang and p.ch = e.a left join singles q on q.lang = e.lang and q.ch = e.b"
query("vocab_boost", sql(_summed_sql(_BOOST, f"edges e {_IN('top_inside')}"), "edges", "top_inside"))(
    lambda x: _summed(A.boost(A.adjacent_weights(x.test, x.model), x.lexicon, 20.0, x.boost_rank)))
query("vocab_divide", sql(_summed_sql(f"{_BOOST} / case when t.a is null and (p.ch is not null or q.ch is not null) then greatest(20.0, ln(1e6 / least(coalesce(p.rank, q.rank), coalesce(q.rank, p.rank)))) else 1.0 end",
                                      f"edges e {_IN('top_inside')} {_ENDS}"), "edges", "top_inside", "singles"))(
    lambda x: _summed(A.split_singles(A.boost(A.adjacent_weights(x.test, x.model), x.lexicon, 20.0, x.boost_rank), x.singles)))
query("vocab_divide_by_rank", sql(_summed_sql(f"{_BOOST} / case when t.a is null and (p.ch is not null or q.ch is not null) then greatest(1.0, ln(1e6 / least(coalesce(p.rank, q.rank), coalesce(q.rank, p.rank)))) else 1.0 end",
                                              f"edges e {_IN('top_inside')} {_ENDS}"), "edges", "top_inside", "singles"))(
    lambda x: _summed(A.split_singles(A.boost(A.adjacent_weights(x.test, x.model), x.lexicon, 20.0, x.boost_rank), x.singles, floor=1.0)))
query("train_boost", sql(_summed_sql(_BOOST, f"edges e {_IN('inside')}"), "edges", "inside"))(lambda x: _summed(A.boost(A.adjacent_weights(x.test, x.model), x.words)))
query("train_divide", sql(_summed_sql(f"{_BOOST} / greatest(1.0, coalesce(p.cnt, 0) / 250.0, coalesce(q.cnt, 0) / 250.0)", f"edges e {_IN('inside')} {_ENDS}"), "edges", "inside", "singles"))(
    lambda x: _summed(A.split_singles_by_count(A.boost(A.adjacent_weights(x.test, x.model), x.words), x.words)))

# --- Laplacians and spectra ----------------------------------------------------


def _part_bands(x) -> DataFrame:
    return A.to_bands(x.part_names, A.adjacent_weights(x.part_names, x.part_model), A.skip_weights(x.part_names, x.part_model))


def _row(name: str, col: str):
    return F.array_join(F.transform(col, lambda v: F.format_number(v, 4)), " ").alias(name)


_LONG = f"""deg as (select sent_id, n, adj, skip, i, 1.0 + coalesce(case when i > 1 then adj[i - 1] end, 0) + coalesce(adj[i], 0) + coalesce(case when i > 2 then skip[i - 2] end, 0) + coalesce(skip[i], 0) as d
  from (select *, unnest(range(1, n + 1)) as i from pbands))"""
_LAP = _LONG + """, lap as (select x.sent_id, x.n, x.i, x.d - 1.0 as l0, coalesce(-x.adj[x.i], 0) as l1, coalesce(-x.skip[x.i], 0) as l2,
  1.0 - 1.0 / x.d as y0, coalesce(-x.adj[x.i] / sqrt(x.d * y.d), 0) as y1, coalesce(-x.skip[x.i] / sqrt(x.d * z.d), 0) as y2
  from deg x left join deg y on y.sent_id = x.sent_id and y.i = x.i + 1 left join deg z on z.sent_id = x.sent_id and z.i = x.i + 2)"""
query("degree", sql(f"+{_LONG} select sent_id, i - 1 as i, round(d, 6) as d from deg", "pbands"))(
    lambda x: L.with_degrees(_part_bands(x)).select("sent_id", F.posexplode("deg").alias("i", "d")).select("sent_id", F.col("i").cast("long").alias("i"), r6("d", "d")))
for key, form, cols in (("laplacian_plain", "plain", ("l0", "l1", "l2")), ("laplacian_sym", "sym", ("y0", "y1", "y2"))):
    query(key, sql(f"+{_LAP} select sent_id, i - 1 as i, {', '.join(f'round({c}, 6) + 0.0 as m{j}' for j, c in enumerate(cols))} from lap", "pbands"))(
        lambda x, form=form: L.laplacian(_part_bands(x), form).select("sent_id", F.posexplode("l0").alias("i", "v"), "l1", "l2").select(
            "sent_id", F.col("i").cast("long").alias("i"), *[(F.round(v, 6) + 0.0).alias(m) for v, m in ((F.col("v"), "m0"), (F.coalesce(F.get("l1", F.col("i")), F.lit(0.0)), "m1"), (F.coalesce(F.get("l2", F.col("i")), F.lit(0.0)), "m2"))]))


def _count_sql(cols: tuple[str, str, str], cuts: list[float], bands: str = "", *names: str) -> str:
    """Eigenvalues within cuts, by a recursion over rows; ``bands`` defines
    ``pbands`` where it is not that of the part names."""
    m0, m1, m2 = cols
    return sql(f"""+{bands}{_LAP}, cuts as (select unnest({cuts}::double[]) as cut),
mat as (select sent_id, n, i, {m0} as m0, {m1} as m1, {m2} as m2 from lap),
run as (select sent_id, cut, 0::bigint as i, 0.0::double as d1, 0.0::double as p1, 0.0::double as q1, 0.0::double as d2, 0.0::double as q2, 0::bigint as k, cut * (1 + 1e-12) + 1e-13 as x from (select distinct sent_id from mat), cuts
  union all select sent_id, cut, i, d, (m1 - p1 * q1 * d1) / d, m2 / d, d1, q1, k + (d < 0)::int, x
  from (select r.sent_id, r.cut, m.i, m.m1, m.m2, r.p1, r.q1, r.d1, r.k, r.x, case when m.m0 - r.x - r.p1 * r.p1 * r.d1 - r.q2 * r.q2 * r.d2 = 0 then 1e-300 else m.m0 - r.x - r.p1 * r.p1 * r.d1 - r.q2 * r.q2 * r.d2 end as d
    from run r join mat m on m.sent_id = r.sent_id and m.i = r.i + 1))
select sent_id, cut, max_by(k, i) as k from run group by sent_id, cut""", *(names or ("pbands",)), recursive=True)


def _bench_bands(edge: str, joins: str, skip: str | None) -> str:
    """``pbands`` of the benchmark sentences with an expression for each weight."""
    skips = (f"left join (select e.sent_id, list({skip} order by e.i) as sk from bskips e {_BY_SET} group by e.sent_id) k using (sent_id)" if skip else "")
    held = "coalesce(any_value(k.sk), [])" if skip else "[]::double[]"
    return f"""pbands as (select p.sent_id, length(p.s)::bigint as n, coalesce(list(b.w order by b.i) filter (b.i is not null), []) as adj, {held} as skip
  from bench p left join (select e.sent_id, e.i, {edge} as w from bedges e {joins}) b using (sent_id) {skips} group by p.sent_id, p.s), """


def _curve(bands: DataFrame, form: str, cuts: list[float]) -> DataFrame:
    rows = L.laplacian(bands, form).withColumn("cut", F.explode(F.array(*[F.lit(c) for c in cuts])))
    return rows.select("sent_id", "cut", L.count_below(F.col("cut")).cast("long").alias("k"))


query("k_by_cut", _count_sql(("l0", "l1", "l2"), [0.15]))(lambda x: _curve(_part_bands(x), "plain", [0.15]))
query("granularity_sweep", _count_sql(("l0", "l1", "l2"), CUTS))(lambda x: _curve(_part_bands(x), "plain", CUTS))
query("granularity_sweep_sym", _count_sql(("y0", "y1", "y2"), [0.01, 0.1, 0.3, 0.7, 1.0]))(lambda x: _curve(_part_bands(x), "sym", [0.01, 0.1, 0.3, 0.7, 1.0]))
query("zero_multiplicity", sql("""select t.sent_id, 1 + coalesce(sum((e.w = 0)::int), 0)::bigint as n_components from test t left join edges e using (sent_id) group by t.sent_id""", "test", "edges"))(
    lambda x: L.components(A.to_bands(x.test, A.adjacent_weights(x.test, x.model), A.skip_weights(x.test, x.model))).select("sent_id", F.col("n_components").cast("long").alias("n_components")))


#: The cuts of the printed runs of the domain method, and of the two methods with dictionaries.
PRINTED_CUTS = [0.1, 0.15, 1.0, 2.0]
_SINGLE = "(p.ch is not null or q.ch is not null)"
_RANKED = f"{_BOOST} / case when t.a is null and {_SINGLE} then greatest(20.0, ln(1e6 / least(coalesce(p.rank, q.rank), coalesce(q.rank, p.rank)))) else 1.0 end"
_COUNTED = f"{_BOOST} / greatest(1.0, coalesce(p.cnt, 0) / 250.0, coalesce(q.cnt, 0) / 250.0)"


def _bench_curve(x, cfg: S.SegmentConfig, cuts: list[float], **given) -> DataFrame:
    return _curve(S.bands_by_joins(x.benchmark, x.model, cfg, **given), cfg.form, cuts)


query("k_domain_printed", _count_sql(("l0", "l1", "l2"), PRINTED_CUTS, _bench_bands(_WEAK, _BY_SET, "case when coalesce(list_has_any(h2, [e.a, e.b, e.c]), false) then 0 else e.w end"),
                                     "bedges", "bskips", "sets"))(
    lambda x: _bench_curve(x, S.DOMAIN, PRINTED_CUTS, sets=x.sets))
query("k_lexicon_printed", _count_sql(("y0", "y1", "y2"), [S.LEXICON.cut], _bench_bands(_RANKED, f"{_IN('top_inside')} {_ENDS}", None), "bedges", "top_inside", "singles"))(
    lambda x: _bench_curve(x, replace(S.LEXICON, max_rank=x.boost_rank), [S.LEXICON.cut], words=x.lexicon, singles=x.singles))
query("k_trained_printed", _count_sql(("y0", "y1", "y2"), [S.TRAINED.cut], _bench_bands(_COUNTED, f"{_IN('inside')} {_ENDS}", None), "bedges", "inside", "singles"))(
    lambda x: _bench_curve(x, S.TRAINED, [S.TRAINED.cut], words=x.words, singles=x.singles))


@query("spectrum")
def _spectrum(x) -> DataFrame:
    """All eigenvalues of each part name's Laplacians, ascending."""
    import numpy as np
    import pandas as pd

    def run(frames):
        for f in frames:
            rows = []
            for sent, adj, skip in zip(f["sent_id"], f["adj"], f["skip"]):
                for form in ("plain", "sym"):
                    v = np.linalg.eigvalsh(K.laplacians(np.array([adj], float), np.array([skip], float).reshape(1, -1), form))[0]
                    rows.append((sent, form, [round(float(max(0, e)), 6) for e in v]))
            yield pd.DataFrame(rows, columns=["sent_id", "form", "eigenvalues"])
    return _part_bands(x).select("sent_id", "adj", "skip").mapInPandas(run, "sent_id string, form string, eigenvalues array<double>")


# --- objectives ----------------------------------------------------------------


def _gold_labels(x) -> DataFrame:
    labels = M.run_labels(units.gold_words(F.col("raw")))
    return _part_bands(x).join(x.part_names.select("sent_id", labels.alias("labels")), "sent_id")


_PLAB = """lab as (select sent_id, i, case when i <= length(split_part(raw, ' ', 1)) then 0 else 1 end as r from (select sent_id, raw, s, unnest(range(1, length(s) + 1)) as i from part_names)),
links as (select sent_id, i + 1 as i, i + 2 as j, w from pedges union all select sent_id, i + 1, i + 3, w from pskips),
cross_w as (select l.sent_id, x.r as r1, y.r as r2, sum(l.w) as w from links l join lab x on x.sent_id = l.sent_id and x.i = l.i join lab y on y.sent_id = l.sent_id and y.i = l.j where x.r <> y.r group by all),
mass as (select b.sent_id, b.r, count(*) as size, sum(d.d) as vol from lab b join deg d on d.sent_id = b.sent_id and d.i = b.i group by all)"""
for key, objective, m in (("ratio_cut", "ratio", "size"), ("normalised_cut", "normalised", "vol")):
    query(key, sql(f"+{_LONG}, {_PLAB} select m.sent_id, round(sum(coalesce(c.w, 0) / m.{m}), 6) as value from mass m left join cross_w c on c.sent_id = m.sent_id group by m.sent_id", "pbands"))(
        lambda x, objective=objective: M.cut_objective(_gold_labels(x), objective).select("sent_id", r6("value", "value")))


def _exact(x, how: str, objective: str = "ratio", k: int = 2) -> DataFrame:
    """Best value over contiguous partitions in k words: by dynamic programming or
    by all masks of boundaries."""
    import numpy as np
    import pandas as pd

    def run(frames):
        for f in frames:
            out = []
            for adj, skip in zip(f["adj"], f["skip"]):
                out.append(round(K.exact_partition(np.array(adj, float), np.array(skip, float), k, objective)[0], 6))
            yield pd.DataFrame({"sent_id": f["sent_id"], "value": out})

    bands = _part_bands(x)
    if how == "dp":
        return bands.select("sent_id", "adj", "skip").mapInPandas(run, "sent_id string, value double")
    # every mask with k - 1 boundaries, names have at most 12 symbols
    n1 = F.col("n").cast("int") - 1
    masks = bands.withColumn("mask", F.explode(F.sequence(F.lit(0), F.call_function("shiftleft", F.lit(1), n1) - 1))).where(F.bit_count("mask") == k - 1)
    labels = F.transform(F.sequence(F.lit(0), n1), lambda i: F.bit_count(F.col("mask").bitwiseAND(F.call_function("shiftleft", F.lit(1), i) - 1)).cast("int"))
    keyed = masks.withColumn("labels", labels).withColumn("name", F.col("sent_id")).withColumn("sent_id", F.concat_ws("#", "sent_id", "mask"))
    return M.cut_objective(keyed, objective).groupBy(F.split("sent_id", "#")[0].alias("sent_id")).agg(r6(F.min("value"), "value"))


_TWO = f"""+{_LONG}, links as (select sent_id, i + 1 as i, i + 2 as j, w from pedges union all select sent_id, i + 1, i + 3, w from pskips),
places as (select sent_id, n, unnest(range(1, n)) as p from pbands),
value as (select p.sent_id, p.p, coalesce(sum(l.w), 0) as w, any_value(p.n) as n from places p left join links l on l.sent_id = p.sent_id and l.i <= p.p and l.j > p.p group by all),
vol as (select p.sent_id, p.p, sum(d.d) filter (d.i <= p.p) as va, sum(d.d) filter (d.i > p.p) as vb from places p join deg d using (sent_id) group by all)"""
query("best_cut_brute", sql(_TWO + " select sent_id, round(min(w / p + w / (n - p)), 6) as value from value group by sent_id", "pbands"))(lambda x: _exact(x, "brute"))
query("best_cut_dp", sql(_TWO + " select sent_id, round(min(w / p + w / (n - p)), 6) as value from value group by sent_id", "pbands"))(lambda x: _exact(x, "dp"))
query("best_ncut_dp", sql(_TWO + " select v.sent_id, round(min(w / va + w / vb), 6) as value from value v join vol using (sent_id, p) group by v.sent_id", "pbands"))(lambda x: _exact(x, "dp", "normalised"))


@query("relaxation_gap")
def _gap(x) -> DataFrame:
    """Ratio cut of the spectral two-way split over the best contiguous value."""
    seg = S.segment(x.part_names, x.part_model, replace(S.DOMAIN, k=2, cluster="contiguous"))
    rows = _part_bands(x).join(seg.select("sent_id", M.run_labels(F.col("words")).alias("labels")), "sent_id")
    return M.cut_objective(rows).join(_exact(x, "dp").withColumnRenamed("value", "best"), "sent_id").select("sent_id", r6("value", "value"), "best", r6(F.col("value") - F.col("best"), "gap"))


# --- segmenters ------------------------------------------------------------------


def predictions(x, method: str, sents: DataFrame | None = None) -> DataFrame:
    """Words of a named method on the test sentences (or others)."""
    sents = x.test if sents is None else sents
    domain = lambda cfg: S.segment(sents, x.model, cfg, sets=x.sets)
    ranked_ = lambda cfg: S.segment(sents, x.model, replace(cfg, max_rank=x.boost_rank), words=x.lexicon, singles=x.singles)
    trained = lambda cfg: S.segment(sents, x.model, cfg, words=x.words, singles=x.singles)
    table = {
        **{f"domain_{c}": lambda c=c: domain(replace(S.DOMAIN, cut=c)) for c in PRINTED_CUTS},
        "domain_soft": lambda: S.segment(sents, x.model, replace(S.DOMAIN, cut=0.3), sets=x.sets.where("set_id = 1")),
        "domain_hard": lambda: S.segment(sents, x.model, replace(S.DOMAIN, cut=0.3), sets=x.sets.where("set_id = 2")),
        "domain_hook": lambda: S.segment(sents, x.model, replace(S.DOMAIN_SCALE, cut=0.3), sets=x.sets, hook=lambda edges: entropy_hook(edges, x.model), by_window=True),
        "learned": lambda: S.segment(sents, x.model, replace(S.LEARNED, cut=x.cut_of("learned")), hook=x.learned.weigh, by_window=True),
        "entropy_order2": lambda: B.pair_entropy_segment(sents, x.model.tri),
        "domain": lambda: domain(replace(S.DOMAIN, cut=0.3)), "domain_no_sets": lambda: S.segment(sents, x.model, replace(S.DOMAIN, cut=0.3)),
        "domain_scale": lambda: domain(replace(S.DOMAIN_SCALE, cut=0.3)), "domain_pp": lambda: domain(replace(S.DOMAIN, cut=0.3, init="pp", jitter=0.001)),
        "domain_sym": lambda: domain(replace(S.DOMAIN, form="sym", cut=0.1)), "domain_no_skip": lambda: domain(replace(S.DOMAIN, use_skip=False, cut=0.3)),
        "domain_gap": lambda: domain(replace(S.DOMAIN, cut="gap")),
        "lexicon": lambda: ranked_(S.LEXICON), "lexicon_dev": lambda: ranked_(replace(S.LEXICON, cut=x.cut_of("lexicon"))),
        "lexicon_in_place": lambda: ranked_(replace(S.LEXICON_SCALE, match="in_place", cut=x.cut_of("lexicon"))),
        "trained": lambda: trained(S.TRAINED), "trained_dev": lambda: trained(replace(S.TRAINED, cut=x.cut_of("trained"))),
        "trained_in_place": lambda: trained(replace(S.TRAINED_SCALE, match="in_place", cut=x.cut_of("trained"))),
        "entropy": lambda: B.entropy_segment(sents, x.model.bi, theta=2.5), "entropy_rise": lambda: B.entropy_segment(sents, x.model.bi, mode="rise"),
        "entropy_both": lambda: B.entropy_segment(sents, x.model.bi, direction="both", theta=2.5),
        "likelihood": lambda: B.likelihood_segment(sents, x.words), "longest": lambda: B.match_segment(sents, x.words), "longest_back": lambda: B.match_segment(sents, x.words, backward=True),
        "threshold": lambda: B.threshold_segment(A.adjacent_weights(sents, x.model), sents, 0.5), "components": lambda: B.components_segment(A.adjacent_weights(sents, x.model), sents),
        "chars": lambda: B.trivial(sents, "chars"), "one": lambda: B.trivial(sents, "one"),
        "tagger": lambda: B.Tagger(x.train).segment(sents),
    }
    return table[method]()


_H = "select lang, {k} as ch, sum(-p * ln(p)) as h from (select lang, a, b, cnt / sum(cnt) over (partition by lang, {k}) as p from bi) group by all"
_H_A = _H.format(k="a")


def _cut_sql(test: str, extra: str, *names: str) -> str:
    """Words of the test sentences from a boundary test on positions e.i."""
    return sql(f"""+ends as (select t.sent_id, t.lang, t.s, e.i + 1 as e from test t join ({extra}) e using (sent_id) where {test} union all select sent_id, lang, s, length(s) from test),
spans as (select sent_id, lang, s, e, coalesce(lag(e) over (partition by sent_id order by e), 0) as a from ends)
select sent_id, lang, string_agg(substr(s, a + 1, e - a), ' ' order by e) as words, count(*) as n_words from spans group by sent_id, lang""", "test", *names)


def entropy_hook(edges: DataFrame, model: C.NgramModel) -> DataFrame:
    """A context-dependent weight: divided by 1 plus the entropy of what
    follows the left symbol."""
    h = B.successor_entropy(model.bi).select("lang", F.col("ch").alias("a"), "h")
    return edges.join(h, ["lang", "a"], "left").withColumn("w", F.col("w") / (1 + F.coalesce("h", F.lit(0.0)))).select(*edges.columns)


query("weight_hook", sql(_summed_sql("e.w / (1 + coalesce(h.h, 0))", f"edges e left join ({_H_A}) h on h.lang = e.lang and h.ch = e.a"), "edges", "bi"))(
    lambda x: _summed(entropy_hook(A.adjacent_weights(x.test, x.model), x.model)))
query("entropy_order2", _cut_sql("e.h > 2.0", "select w.sent_id, w.i, h.h from win w join (select lang, a, b, sum(-p * ln(p)) as h from (select lang, a, b, cnt / sum(cnt) over (partition by lang, a, b) as p from tri) group by all) h"
                                 " on h.lang = w.lang and h.a = w.o and h.b = w.a", "win", "tri"))(lambda x: _flat(predictions(x, "entropy_order2")))
query("cuts_chosen_on_dev")(lambda x: x.spark.createDataFrame([(m, c, f) for m in ("lexicon", "trained") for c, f in x.dev_scores(m)], "method string, cut double, f1 double"))


def _flat(words: DataFrame) -> DataFrame:
    return words.select("sent_id", "lang", F.array_join("words", " ").alias("words"), F.size("words").cast("long").alias("n_words"))


for key, method in (("segment_domain", "domain"), *((f"segment_domain_cut_{str(c).replace('.', '_')}", f"domain_{c}") for c in PRINTED_CUTS), ("segment_learned", "learned"), ("segment_hook", "domain_hook"), ("segment_domain_scale", "domain_scale"), ("kmeans_pp", "domain_pp"), ("segment_lexicon", "lexicon"), ("segment_trained", "trained"),
                    ("segment_in_place", "trained_in_place"), ("adaptive_cut", "domain_gap"), ("max_likelihood", "likelihood"), ("long_match", "longest"), ("long_match_back", "longest_back")):
    query(key)(lambda x, method=method: _flat(predictions(x, method)))


query("weight_threshold", _cut_sql("e.w < 0.5", "select * from edges", "edges"))(lambda x: _flat(predictions(x, "threshold")))
query("components_only", _cut_sql("e.w = 0", "select * from edges", "edges"))(lambda x: _flat(predictions(x, "components")))
query("entropy_boundary", _cut_sql("e.h > 2.5", f"select w.sent_id, w.i, h.h from win w join ({_H.format(k='a')}) h on h.lang = w.lang and h.ch = w.a", "win", "bi"))(lambda x: _flat(predictions(x, "entropy")))
query("entropy_both", _cut_sql("e.h > 2.5 or e.k > 2.5", f"select w.sent_id, w.i, coalesce(h.h, 0) as h, coalesce(k.h, 0) as k from win w left join ({_H.format(k='a')}) h on h.lang = w.lang and h.ch = w.a left join ({_H.format(k='b')}) k on k.lang = w.lang and k.ch = w.b", "win", "bi"))(
    lambda x: _flat(predictions(x, "entropy_both")))
query("entropy_rise", _cut_sql("e.h > coalesce(e.g, 0) + 1e-9", f"select w.sent_id, w.i, coalesce(h.h, 0) as h, g.h as g from win w left join ({_H.format(k='a')}) h on h.lang = w.lang and h.ch = w.a left join ({_H.format(k='a')}) g on g.lang = w.lang and g.ch = w.o", "win", "bi"))(
    lambda x: _flat(predictions(x, "entropy_rise")))
query("every_char", sql("select sent_id, lang, array_to_string(string_split(s, ''), ' ') as words, length(s) as n_words from test", "test"))(lambda x: _flat(predictions(x, "chars")))
query("whole_sentence", sql("select sent_id, lang, s as words, 1::bigint as n_words from test", "test"))(lambda x: _flat(predictions(x, "one")))
query("gold_words", sql("select sent_id, lang, string_agg(word, ' ' order by w_no) as words, count(*) as n_words from gold group by all", "gold"))(lambda x: _flat(M.gold(x.test)))
query("concatenation", sql("select sent_id, s as joined from test", "test"))(lambda x: predictions(x, "domain_scale").select("sent_id", F.array_join("words", "").alias("joined")))


@query("supervised_tagger")
def _tagger(x) -> DataFrame:
    return _flat(predictions(x, "tagger"))


@query("levels")
def _levels(x) -> DataFrame:
    """Coarse words, and fine words inside each of them."""
    coarse = predictions(x, "domain_scale").select("sent_id", "lang", F.posexplode("words").alias("w_no", "s"))
    keyed = coarse.withColumn("sent_id", F.concat_ws("/", "sent_id", F.col("w_no").cast("string")))
    fine = S.segment(keyed, x.model, replace(S.DOMAIN_SCALE, cut=1.0), sets=x.sets)
    return fine.select("sent_id", "lang", F.col("s").alias("coarse"), F.array_join("words", " ").alias("fine"))


# --- measures --------------------------------------------------------------------

_SPANS = """ends as (select t.sent_id, t.lang, t.s, e.i + 1 as e from test t join edges e using (sent_id) where e.w < 0.5 union all select sent_id, lang, s, length(s) from test),
pred as (select sent_id, lang, coalesce(lag(e) over (partition by sent_id order by e), 0) as a, e from ends),
hits as (select p.sent_id from pred p join gold g on g.sent_id = p.sent_id and g.a = p.a and g.e = p.e)"""


def _round_scores(df: DataFrame) -> DataFrame:
    return df.select(*[c for c in df.columns if c not in ("precision", "recall", "f1")], *[r6(F.col(c), c) for c in ("precision", "recall", "f1")])


_PRF6 = "tp, n_pred, n_gold, round(tp / n_pred, 6) as precision, round(tp / n_gold, 6) as recall, round(case when tp > 0 then 2 * (tp / n_pred) * (tp / n_gold) / (tp / n_pred + tp / n_gold) else 0.0 end, 6) as f1"
query("score_words", sql(f"""+{_SPANS} select lang, {_PRF6} from (select lang, count(*) as n_pred, (select count(*) from gold g where g.lang = p.lang) as n_gold,
  (select count(*) from hits h join test t using (sent_id) where t.lang = p.lang) as tp from pred p group by lang)""", "test", "edges", "gold"))(
    lambda x: _round_scores(M.score_words(predictions(x, "threshold"), M.gold(x.test))))
query("boundary_prf", sql(f"""+{_SPANS}, pb as (select p.sent_id, p.lang, p.e from pred p join test t using (sent_id) where p.e < length(t.s)), gb as (select g.sent_id, g.lang, g.e from gold g join test t using (sent_id) where g.e < length(t.s))
select lang, {_PRF6} from (select l.lang, (select count(*) from pb where pb.lang = l.lang) as n_pred, (select count(*) from gb where gb.lang = l.lang) as n_gold,
  (select count(*) from pb join gb using (sent_id, e) where pb.lang = l.lang) as tp from (select distinct lang from test) l)""", "test", "edges", "gold"))(
    lambda x: _round_scores(M.score_bounds(predictions(x, "threshold"), M.gold(x.test))))
query("granularity_stats", sql("""select lang, count(distinct sent_id) as sentences, count(*) as n_words, round(count(*) / count(distinct sent_id), 6) as words_per_sentence,
  round(avg(length(word)), 6) as mean_len, quantile_cont(length(word), 0.5) as median_len, max(length(word)) as max_len from gold group by lang""", "gold"))(
    lambda x: M.granularity_stats(M.gold(x.test)).withColumns({c: F.round(c, 6) for c in ("words_per_sentence", "mean_len")}))
query("merge_split_errors", sql(f"""+{_SPANS}, kinds as (select p.lang, case when exists (select 1 from gold g where g.sent_id = p.sent_id and g.a = p.a and g.e = p.e) then 'right'
  when exists (select 1 from gold g where g.sent_id = p.sent_id and g.a <= p.a and g.e >= p.e) then 'split'
  when exists (select 1 from gold g where g.sent_id = p.sent_id and g.a = p.a) and exists (select 1 from gold g where g.sent_id = p.sent_id and g.e = p.e) then 'merged' else 'crossing' end as kind from pred p)
select lang, kind, count(*) as n from kinds group by all""", "test", "edges", "gold"))(lambda x: M.error_types(predictions(x, "threshold"), M.gold(x.test)))
query("term_list", sql("""select lang, word, cnt, rank from (select lang, word, count(*) as cnt, row_number() over (partition by lang order by count(*) desc, word) as rank from gold
  where length(word) >= 2 and regexp_matches(word, '^\\p{L}+$') group by lang, word having count(*) >= 2) where rank <= 20""", "gold"))(
    lambda x: M.top_terms(M.gold(x.test)).withColumn("rank", F.col("rank").cast("long")))
query("fragmentation")(lambda x: M.fragmentation(predictions(x, "domain")))
query("form_effect")(lambda x: M.form_effect(predictions(x, "domain"), predictions(x, "domain_sym")))


@query("difference_table")
def _difference(x) -> DataFrame:
    """Benchmark sentences where the two dictionary methods differ."""
    return M.difference_table(predictions(x, "trained_dev", x.benchmark), predictions(x, "lexicon_dev", x.benchmark), M.gold(x.benchmark))


@query("post_dates")
def _dates(x) -> DataFrame:
    """Numbers and dates with marks inside that post-processing kept whole in the
    output of the method with training words."""
    words = predictions(x, "trained").select("lang", F.explode("words").alias("word"))
    return words.where(F.col("word").rlike("^[0-9]+[.,/:-][0-9]")).groupBy("lang", "word").agg(F.count("*").alias("n"))


@query("post_numbers")
def _post(x) -> DataFrame:
    """Digits and date marks of gold words put back together."""
    import pandas as pd

    def run(frames):
        for f in frames:
            yield pd.DataFrame({"sent_id": f["sent_id"], "words": [" ".join(K.join_numbers_dates(list(w))) for w in f["words"]]})
    digits = predictions(x, "chars").where(F.col("s").rlike("[0-9]"))
    return digits.select("sent_id", "words").mapInPandas(run, "sent_id string, words string")
