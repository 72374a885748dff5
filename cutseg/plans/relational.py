"""Operators around the methods: joins, windows, sets, functions, streams."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window as W, functions as F

from cutseg.functions import sqlapi, units
from cutseg.operators import affinity as A, metrics as M, segment as S
from cutseg.operators.corpus import ngram_counts, ranked
from cutseg.plans.methods import predictions, query, r6, _SPANS
from cutseg.plans.twins import sql
from cutseg.sources import tables
from cutseg.streaming import streams

# --- scans, filters, joins --------------------------------------------------------

query("scan_documents", "select doc_id, lang, source, n_chars from documents where lang in ('de', 'fr') and n_chars between 500 and 2000")(
    lambda x: x.table("documents").where(F.col("lang").isin("de", "fr") & F.col("n_chars").between(500, 2000)).select("doc_id", "lang", "source", "n_chars"))
query("filter_usable", sql("select lang, g, cnt from bi_g where regexp_matches(g, '^\\p{L}+$')", "bi_g"))(lambda x: x.grams[2].where(F.col("g").rlike("^\\p{L}+$")))
query("filter_lang", sql("select sent_id, lang, s from test where lang <> 'en' and length(s) >= 20", "test"))(
    lambda x: x.test.where((F.col("lang") != "en") & (F.length("s") >= 20)).select("sent_id", "lang", "s"))
query("join_session_interval", """with s as (select user_id, min(epoch_us(ts)) as a, max(epoch_us(ts)) as b from (select *, sum(new) over (partition by user_id order by ts, event_id) as g from
  (select *, case when epoch_us(ts) - lag(epoch_us(ts)) over (partition by user_id order by ts, event_id) < 43200000000 then 0 else 1 end as new from events)) group by user_id, g)
select s.user_id, s.a as start_us, count(*) as n, count(*) filter (event_type = 'purchase') as purchases from events e join s on e.user_id = s.user_id and epoch_us(e.ts) between s.a and s.b group by s.user_id, s.a""")(
    lambda x: _events_in_sessions(x))
query("join_bigram_broadcast", sql("select w.lang, count(*) as hits, round(sum(b.z), 4) as z from win w join bi b on b.lang = w.lang and b.a = w.a and b.b = w.b group by w.lang", "win", "bi"))(
    lambda x: A.windows(x.test).join(F.broadcast(x.model.bi.select("lang", "a", "b", "z")), ["lang", "a", "b"]).groupBy("lang").agg(F.count("*").alias("hits"), F.round(F.sum("z"), 4).alias("z")))
query("join_trigram_merge", sql("select w.lang, count(*) as hits, round(sum(t.z), 4) as z from win w join tri t on t.lang = w.lang and t.a = w.a and t.b = w.b and t.c = w.x group by w.lang", "win", "tri"))(
    lambda x: A.windows(x.test).withColumnRenamed("x", "c").join(x.model.tri.select("lang", "a", "b", "c", "z").hint("merge"), ["lang", "a", "b", "c"]).groupBy("lang").agg(F.count("*").alias("hits"), F.round(F.sum("z"), 4).alias("z")))


def _span_rows(words: DataFrame) -> DataFrame:
    s = words.select("sent_id", "lang", F.posexplode(units.spans(F.col("words"))).alias("w_no", "x"))
    return s.select("sent_id", "lang", "w_no", F.floor(F.col("x") / 1048576).alias("a"), (F.col("x") % 1048576).alias("e"))


query("join_span_overlap", sql(f"+{_SPANS} select p.lang, count(*) as overlaps from pred p join gold g on g.sent_id = p.sent_id and p.a < g.e and g.a < p.e group by p.lang", "test", "edges", "gold"))(
    lambda x: _span_rows(predictions(x, "threshold")).alias("p").join(_span_rows(M.gold(x.test)).alias("g"), F.expr("p.sent_id = g.sent_id and p.a < g.e and g.a < p.e")).groupBy("p.lang").agg(F.count("*").alias("overlaps")))
query("join_span_range", sql(f"+{_SPANS} select p.lang, count(*) as contained from pred p join gold g on g.sent_id = p.sent_id and p.a >= g.a and p.e <= g.e group by p.lang", "test", "edges", "gold"))(
    lambda x: _span_rows(predictions(x, "threshold")).alias("p").join(_span_rows(M.gold(x.test)).alias("g"), F.expr("p.sent_id = g.sent_id and p.a >= g.a and p.e <= g.e")).groupBy("p.lang").agg(F.count("*").alias("contained")))
def _events_in_sessions(x) -> DataFrame:
    """Events inside each session of their user: sides meet by the user, the
    interval is a condition inside."""
    us = lambda c: F.unix_micros(F.col(c).cast("timestamp"))
    # a session window ends its gap of 12 hours after its last event
    s = streams.sessions(x.table("events")).select(F.col("user_id").alias("u"), us("start").alias("a"), (us("end") - 43_200_000_000).alias("b"))
    e = x.table("events").select("user_id", "event_type", us("ts").alias("t"))
    inside = e.join(s, (F.col("user_id") == F.col("u")) & F.col("t").between(F.col("a"), F.col("b")))
    return inside.groupBy("user_id", F.col("a").alias("start_us")).agg(F.count("*").alias("n"), F.count_if(F.col("event_type") == "purchase").alias("purchases"))


query("semi_labelled", "select d.doc_id, d.lang from documents d where exists (select 1 from labels l where l.doc_id = d.doc_id and l.quality = 1)")(
    lambda x: x.table("documents").join(x.table("labels").where("quality = 1"), "doc_id", "left_semi").select("doc_id", "lang"))
query("anti_contaminated", sql("select doc_id from train_docs", "train_docs"))(lambda x: tables.corpus(x.spark, x.dir, "train").select("doc_id"))
query("oov_words", sql("select distinct lang, word from gold g where regexp_matches(word, '^\\p{L}+$') and not exists (select 1 from words w where w.lang = g.lang and w.word = g.word)", "gold", "words"))(
    lambda x: M.gold(x.test).select("lang", F.explode("words").alias("word")).where(F.col("word").rlike("^\\p{L}+$")).distinct().join(x.words, ["lang", "word"], "left_anti"))
query("outer_pred_gold", sql(f"+{_SPANS} select count(*) as n, count(p.e) as in_pred, count(g.e) as in_gold from pred p full outer join gold g on g.sent_id = p.sent_id and g.a = p.a and g.e = p.e", "test", "edges", "gold"))(
    lambda x: _span_rows(predictions(x, "threshold")).alias("p").join(_span_rows(M.gold(x.test)).alias("g"), F.expr("p.sent_id = g.sent_id and p.a = g.a and p.e = g.e"), "full_outer")
    .agg(F.count("*").alias("n"), F.count("p.e").alias("in_pred"), F.count("g.e").alias("in_gold")))
query("cross_cuts", sql("select sent_id, cut from part_names, (select unnest([0.1, 0.15, 2.0]::double[]) as cut)", "part_names"))(
    lambda x: x.part_names.select("sent_id", F.explode(F.array(*[F.lit(c) for c in (0.1, 0.15, 2.0)])).alias("cut")))
@query("asof_model_version", """select o_orderkey, v.event_id as version from orders o asof left join (select event_id, user_id, ts from events where event_type = 'purchase' qualify row_number() over (partition by user_id, ts order by event_id desc) = 1) v
  on o.o_custkey = v.user_id and o.o_orderdate >= v.ts""")
def _asof(x) -> DataFrame:
    """Latest purchase event of the customer at or before each order."""
    v = x.table("events").where("event_type = 'purchase'").select(F.col("user_id").alias("k"), F.col("ts").cast("timestamp").alias("t"), F.col("event_id").alias("version"), F.lit(0).alias("side"), F.lit(None).cast("long").alias("o_orderkey"))
    o = x.table("orders").select(F.col("o_custkey").alias("k"), F.col("o_orderdate").cast("timestamp").alias("t"), F.lit(None).cast("long").alias("version"), F.lit(1).alias("side"), "o_orderkey")
    w = W.partitionBy("k").orderBy("t", "side", "version").rowsBetween(W.unboundedPreceding, 0)
    return v.unionByName(o).withColumn("version", F.last("version", ignorenulls=True).over(w)).where("side = 1").select("o_orderkey", "version")


# --- aggregation -------------------------------------------------------------------

query("agg_collect_words", sql("select lang, count(distinct word) as n, min(word) as first, max(word) as last from gold group by lang", "gold"))(
    lambda x: M.gold(x.test).select("lang", F.explode("words").alias("word")).groupBy("lang").agg(F.countDistinct("word").alias("n"), F.min("word").alias("first"), F.max("word").alias("last")))
query("distinct_vocab", sql("select lang, count(*) as n from words group by lang", "words"))(lambda x: x.words.groupBy("lang").agg(F.count("*").alias("n")))
query("approx_vocab")(lambda x: x.train.select("lang", F.explode(units.gold_words(F.col("raw"))).alias("w")).groupBy("lang").agg(F.approx_count_distinct("w").alias("n")))


def _slices(x) -> DataFrame:
    return x.test.select("lang", "source", F.size(units.gold_words(F.col("raw"))).cast("long").alias("words"))


_SLICES = "(select t.lang, t.source, len(regexp_extract_all(raw, '[\\p{L}\\p{N}]+|[^\\s\\p{L}\\p{N}]')) as words from test t)"
for key, how, form in (("score_cube", "cube", "cube (lang, source)"), ("score_rollup", "rollup", "rollup (lang, source)")):
    query(key, sql(f"select lang, source, sum(words)::bigint as words, count(*) as n from {_SLICES} group by {form}", "test"))(
        lambda x, how=how: getattr(_slices(x), how)("lang", "source").agg(F.sum("words").alias("words"), F.count("*").alias("n")))
query("score_grouping_sets", sql(f"select lang, source, sum(words)::bigint as words from {_SLICES} group by grouping sets ((lang), (source), ())", "test"))(
    lambda x: _slices(x).groupingSets([["lang"], ["source"], []], "lang", "source").agg(F.sum("words").alias("words")))
query("pivot_scores", sql(f"select source, sum(words) filter (lang = 'en')::bigint as en, sum(words) filter (lang = 'fr')::bigint as fr, sum(words) filter (lang = 'de')::bigint as de, sum(words) filter (lang = 'es')::bigint as es from {_SLICES} group by source", "test"))(
    lambda x: _slices(x).groupBy("source").pivot("lang", ["en", "fr", "de", "es"]).agg(F.sum("words")))
query("unpivot_counts", sql("select lang, 'n_uni' as what, count(*) as n from uni_g group by lang union all select lang, 'n_bi', count(*) from bi_g group by lang", "uni_g", "bi_g"))(
    lambda x: x.grams[1].groupBy("lang").agg(F.count("*").alias("n_uni")).join(x.grams[2].groupBy("lang").agg(F.count("*").alias("n_bi")), "lang").unpivot("lang", ["n_uni", "n_bi"], "what", "n"))
query("udaf_entropy", sql("select lang, a, round(sum(-p * ln(p)), 6) + 0.0 as h from (select lang, a, cnt / sum(cnt) over (partition by lang, a) as p from bi) group by all", "bi"))(
    lambda x: x.model.bi.groupBy("lang", "a").agg((F.round(sqlapi.entropy_builtin("cnt"), 6) + 0.0).alias("h")))
query("udaf_entropy_pandas")(lambda x: x.model.bi.groupBy("lang", "a").agg(sqlapi.entropy_udaf("cnt").alias("h")))

# --- windows -----------------------------------------------------------------------

_BY_COUNT = lambda: W.partitionBy("lang").orderBy(F.desc("cnt"))
query("rank_vocab", sql("select lang, g, rank() over (partition by lang order by cnt desc) as r from bi_g", "bi_g"))(
    lambda x: x.grams[2].select("lang", "g", F.rank().over(_BY_COUNT()).cast("long").alias("r")))
query("dense_rank_vocab", sql("select lang, g, dense_rank() over (partition by lang order by cnt desc) as r from bi_g", "bi_g"))(
    lambda x: x.grams[2].select("lang", "g", F.dense_rank().over(_BY_COUNT()).cast("long").alias("r")))
query("percent_rank_vocab", sql("select lang, g, round(percent_rank() over (partition by lang order by cnt desc), 6) as r from bi_g", "bi_g"))(
    lambda x: x.grams[2].select("lang", "g", r6(F.percent_rank().over(_BY_COUNT()), "r")))
query("ntile_vocab", sql("select lang, g, ntile(4) over (partition by lang order by cnt desc, g) as q from bi_g", "bi_g"))(
    lambda x: x.grams[2].select("lang", "g", F.ntile(4).over(W.partitionBy("lang").orderBy(F.desc("cnt"), "g")).cast("long").alias("q")))
query("neighbours_lag_lead", sql("select sent_id, i, a, lag(a) over (partition by sent_id order by i) as before, lead(a) over (partition by sent_id order by i) as behind from pwin", "pwin"))(
    lambda x: A.windows(x.part_names).select("sent_id", F.col("i").cast("long").alias("i"), "a", F.lag("a").over(W.partitionBy("sent_id").orderBy("i")).alias("before"), F.lead("a").over(W.partitionBy("sent_id").orderBy("i")).alias("behind")))
query("running_offset", sql("select sent_id, w_no, a, e from gold", "gold"))(
    lambda x: _span_rows(M.gold(x.test)).select("sent_id", F.col("w_no").cast("long").alias("w_no"), "a", "e"))
query("moving_weight", sql("select sent_id, i, round(avg(w) over (partition by sent_id order by i rows between 2 preceding and 2 following), 6) as m from pedges", "pedges"))(
    lambda x: A.adjacent_weights(x.part_names, x.part_model).select("sent_id", F.col("i").cast("long").alias("i"), r6(F.avg("w").over(W.partitionBy("sent_id").orderBy("i").rowsBetween(-2, 2)), "m")))
query("range_frame_events", "select event_id, count(*) over (partition by user_id order by epoch_us(ts) range between 86400000000 preceding and current row) as n from events")(
    lambda x: x.table("events").select("event_id", F.count("*").over(W.partitionBy("user_id").orderBy(F.unix_micros(F.col("ts").cast("timestamp"))).rangeBetween(-86_400_000_000, 0)).alias("n")))

# --- order, sets, sampling -----------------------------------------------------------

query("topk_global", sql("select lang, word, cnt from words order by cnt desc, lang, word limit 25", "words"))(lambda x: x.words.orderBy(F.desc("cnt"), "lang", "word").limit(25))
query("topk_per_lang", sql("select lang, word, rank from lexicon where rank <= 10", "lexicon"))(lambda x: ranked(x.words).where("rank <= 10").withColumn("rank", F.col("rank").cast("long")))
query("longest_words", sql("select lang, word, length(word) as n from words order by length(word) desc, lang, word limit 20", "words"))(
    lambda x: x.words.select("lang", "word", F.length("word").cast("long").alias("n")).orderBy(F.desc("n"), "lang", "word").limit(20))


def _vocab(x, sents: DataFrame) -> DataFrame:
    return sents.select("lang", F.explode(units.gold_words(F.col("raw"))).alias("word")).distinct()


_V = lambda t: f"select distinct lang, unnest(regexp_extract_all(raw, '[\\p{{L}}\\p{{N}}]+|[^\\s\\p{{L}}\\p{{N}}]')) as word from {t}"
for key, op, how in (("vocab_union", "union", "union"), ("vocab_intersect", "intersect", "intersect"), ("vocab_except", "except", "subtract")):
    query(key, sql(f"{_V('train')} {op} {_V('test')}", "train", "test"))(
        lambda x, how=how: (_vocab(x, x.train).union(_vocab(x, x.test)).distinct() if how == "union" else getattr(_vocab(x, x.train), how)(_vocab(x, x.test))))
for key, op, how in (("grams_intersect_all", "intersect all", "intersectAll"), ("grams_except_all", "except all", "exceptAll")):
    query(key, sql(f"select a, b from pwin {op} select a, b from bi", "pwin", "bi"))(lambda x, how=how: getattr(A.windows(x.part_names).select("a", "b"), how)(x.model.bi.select("a", "b")))
query("sample_hash", "select doc_id from documents where (doc_id * 2654435761) % 4294967296 < 429496730")(
    lambda x: x.table("documents").where((F.col("doc_id") * 2654435761) % 4294967296 < 429496730).select("doc_id"))
query("dedup_sentences", sql("select lang, s, min(sent_id) as sent_id, count(*) as copies from test group by lang, s", "test"))(
    lambda x: x.test.groupBy("lang", "s").agg(F.min("sent_id").alias("sent_id"), F.count("*").alias("copies")))

# --- functions -----------------------------------------------------------------------

query("fn_string", "select p_partkey, upper(p_name) as u, reverse(p_name) as r, levenshtein(p_brand, p_type) as d, translate(p_name, 'aeiou', '12345') as t, concat_ws('-', p_brand, p_size::varchar) as c, length(p_name) as n from part")(
    lambda x: x.table("part").select("p_partkey", F.upper("p_name").alias("u"), F.reverse("p_name").alias("r"), F.levenshtein("p_brand", "p_type").cast("long").alias("d"),
                                     F.translate("p_name", "aeiou", "12345").alias("t"), F.concat_ws("-", "p_brand", F.col("p_size").cast("string")).alias("c"), F.length("p_name").cast("long").alias("n")))
query("fn_date", "select strftime(date_trunc('month', o_orderdate), '%Y-%m') as m, count(*) as n, min(epoch_us(o_orderdate)) as first_us from orders group by 1")(
    lambda x: x.table("orders").groupBy(F.date_format(F.date_trunc("month", "o_orderdate"), "yyyy-MM").alias("m")).agg(F.count("*").alias("n"), F.min(F.unix_micros(F.col("o_orderdate").cast("timestamp"))).alias("first_us")))
query("fn_math", "select l_orderkey, l_linenumber, round(ln(l_extendedprice), 6) as x, round(sqrt(l_quantity), 6) as y, greatest(l_discount, l_tax) as g from lineitem")(
    lambda x: x.table("lineitem").select("l_orderkey", "l_linenumber", r6(F.log("l_extendedprice"), "x"), r6(F.sqrt("l_quantity"), "y"), F.greatest("l_discount", "l_tax").alias("g")))
query("fn_array", sql("select sent_id, array_to_string(list_transform(string_split(s, ''), lambda c: upper(c)), '.') as up, len(list_filter(string_split(s, ''), lambda c: c in ('a', 'e'))) as vowels from part_names", "part_names"))(
    lambda x: x.part_names.select("sent_id", F.array_join(F.transform(units.symbols(F.col("s")), F.upper), ".").alias("up"), F.size(F.filter(units.symbols(F.col("s")), lambda c: c.isin("a", "e"))).cast("long").alias("vowels")))
query("fn_map", sql("select g.lang, g.g, coalesce(case s.set_id when 1 then 4.0 when 2 then 80.0 end, 1.0)::double as divisor from uni_g g left join sets s on s.lang = g.lang and s.ch = g.g", "uni_g", "sets"))(
    lambda x: x.grams[1].join(F.broadcast(x.sets.groupBy("lang").agg(F.map_from_entries(F.collect_list(F.struct("ch", F.when(F.col("set_id") == 1, 4.0).otherwise(80.0).alias("d")))).alias("m"))), "lang", "left")
    .select("lang", "g", F.coalesce(F.element_at("m", F.col("g")), F.lit(1.0)).alias("divisor")))
query("fn_json", "select event_id, json_extract_string(props, '$.k') as k from events")(lambda x: x.table("events").select("event_id", F.get_json_object("props", "$.k").alias("k")))

# --- batch twins of the stream windows --------------------------------------------------

query("win_tumbling", "select epoch_us(time_bucket(interval 1 hour, ts, timestamp '1970-01-01')) as start_us, event_type, count(*) as n, round(sum(value), 4) as total from events group by all")(
    lambda x: streams.windowed_counts(x.table("events"), "1 hour").select(F.unix_micros(F.col("start").cast("timestamp")).alias("start_us"), "event_type", "n", F.round("total", 4).alias("total")))
query("win_sliding", """select epoch_us(b) + k * 21600000000 as start_us, event_type, count(*) as n from (select time_bucket(interval 6 hour, ts, timestamp '1970-01-01') as b, event_type from events), (select unnest([0, -1, -2, -3]) as k) group by all""")(
    lambda x: streams.windowed_counts(x.table("events"), "1 day", "6 hours").select(F.unix_micros(F.col("start").cast("timestamp")).alias("start_us"), "event_type", "n"))
query("win_session", """select user_id, min(epoch_us(ts)) as start_us, count(*) as n from (select *, sum(new) over (partition by user_id order by ts, event_id) as g from
  (select *, case when epoch_us(ts) - lag(epoch_us(ts)) over (partition by user_id order by ts, event_id) < 43200000000 then 0 else 1 end as new from events)) group by user_id, g""")(
    lambda x: streams.sessions(x.table("events")).select("user_id", F.unix_micros(F.col("start").cast("timestamp")).alias("start_us"), "n"))


# --- streams and the SQL surface ----------------------------------------------------------


@query("stream_segment")
def _stream_segment(x) -> DataFrame:
    docs = x.ws.table(x.documents.repartition(4), "stream-docs")
    stream = streams.document_stream(x.spark, docs.inputFiles()[0].rsplit("/", 1)[0])
    out = streams.run_to_end(streams.segment_stream(stream, x.model, S.DOMAIN_SCALE, sets=x.sets), "segment")
    return out.select("sent_id", "lang", "k", F.array_join("words", " ").alias("words"))


@query("stream_counts", sql("select lang, substr(s, i, 2) as g, count(*) as cnt from (select lang, s, unnest(range(1, length(s))) as i from all_sents) group by all", "all_sents"))
def _stream_counts(x) -> DataFrame:
    docs = x.ws.table(x.documents.repartition(3), "stream-count-docs")
    counts = streams.RunningCounts(x.spark)
    stream = streams.document_stream(x.spark, docs.inputFiles()[0].rsplit("/", 1)[0])
    stream.writeStream.foreachBatch(counts.update).option("checkpointLocation", f"{counts.ws.root}-log").trigger(availableNow=True).start().awaitTermination()
    return counts.total()


@query("stream_windows", "select epoch_us(time_bucket(interval 1 hour, ts, timestamp '1970-01-01')) as start_us, event_type, count(*) as n from events group by all")
def _stream_windows(x) -> DataFrame:
    """The same hourly counts from a stream, all updates kept to the end."""
    e = x.ws.table(x.table("events").withColumn("ts", F.col("ts").cast("timestamp")), "stream-events")
    stream = x.spark.readStream.schema(e.schema).parquet(e.inputFiles()[0].rsplit("/", 1)[0])
    out = streams.run_to_end(streams.windowed_counts(stream, "1 hour"), "windows", "complete")
    return out.select(F.unix_micros("start").alias("start_us"), "event_type", "n")


@query("stream_late", """with h as (select time_bucket(interval 1 hour, ts, timestamp '1970-01-01') as b, event_type from events), top as (select max(ts) as m from events)
select epoch_us(b) as start_us, event_type, count(*) as n from h, top where b + interval 1 hour <= m - interval 2 hour group by all""")
def _stream_late(x) -> DataFrame:
    """Hourly counts in append mode: a window comes out once the watermark, two
    hours behind the latest event, has passed its end."""
    e = x.ws.table(x.table("events").withColumn("ts", F.col("ts").cast("timestamp")).repartition(1), "stream-late-events")
    stream = x.spark.readStream.schema(e.schema).parquet(e.inputFiles()[0].rsplit("/", 1)[0])
    out = streams.run_to_end(streams.windowed_counts(stream, "1 hour", late="2 hours"), "late")
    return out.select(F.unix_micros("start").alias("start_us"), "event_type", "n")


@query("udf_segment")
def _udf(x) -> DataFrame:
    sqlapi.register(x.spark, x.part_model, S.DOMAIN_SCALE)
    x.part_names.createOrReplaceTempView("cutseg_part_names")
    return x.spark.sql("select sent_id, array_join(segment_udf(lang, s), ' ') as words from cutseg_part_names")


@query("udtf_words")
def _udtf(x) -> DataFrame:
    sqlapi.register(x.spark, x.part_model, S.DOMAIN_SCALE)
    x.part_names.createOrReplaceTempView("cutseg_part_names")
    return x.spark.sql("select p.sent_id, w.* from cutseg_part_names p, lateral segment_words(p.lang, p.s, 1.0) w")


@query("sql_ngrams", sql("select lang, g, cnt from bi_g", "bi_g"))
def _sql_ngrams(x) -> DataFrame:
    x.train.createOrReplaceTempView("cutseg_train")
    return x.spark.sql("""select lang, g, count(*) as cnt from (select lang, explode(transform(sequence(0, size(y) - 2), i -> concat(y[i], y[i + 1]))) as g
      from (select lang, filter(split(s, ''), c -> c <> '') as y from cutseg_train where length(s) >= 2)) group by lang, g""")


query("distinct_windows", sql("select lang, count(*) as windows, count(distinct (o, a, b, x)) as kinds from win group by lang", "win"))(
    lambda x: A.windows(x.test).groupBy("lang").agg(F.count("*").alias("windows"), F.countDistinct("o", "a", "b", "x").alias("kinds")))
query("gram_count_check", sql("select lang, count(*) as n, sum(cnt)::bigint as total from tri_g group by lang", "tri_g"))(
    lambda x: ngram_counts(x.train, 3).groupBy("lang").agg(F.count("*").alias("n"), F.sum("cnt").alias("total")))
