"""Relational, streaming and function operators around the methods, each on a given table."""

from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from curator.functions.text import n_tokens, strip_html
from curator.functions.vectors import dot
from curator.functions.workspace import shared_root, stash
from curator.operators import lloyd
from curator.sources.tables import corpus_vec, table, write_partitioned
from curator.sqlsurface import Shingles, entropy_of, install, vec_dot
from curator.streaming import streams

QUERIES: dict = {}
ORACLES: dict = {}


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql is not None:
            ORACLES[f.__name__] = sql
        return f

    return add


def tables(spark: SparkSession, d: str, *names: str) -> list[DataFrame]:
    return [table(spark, d, n) for n in names]


def n() -> Column:
    return F.count(F.lit(1)).alias("n")


@query("SELECT doc_id, lang FROM documents")
def op_scan_project(spark, d):
    return table(spark, d, "documents").select("doc_id", "lang")


@query("SELECT doc_id, n_chars FROM documents WHERE lang = 'de' AND n_chars BETWEEN 500 AND 2000")
def op_filter_pushdown(spark, d):
    return table(spark, d, "documents").where((F.col("lang") == "de") & F.col("n_chars").between(500, 2000)).select("doc_id", "n_chars")


@query("SELECT doc_id, contains(text, 'http') AS has_url, regexp_matches(text, '[0-9]{3}') AS has_number, lang IN ('en', 'fr') AS western FROM documents")
def op_predicates_text(spark, d):
    return table(spark, d, "documents").select("doc_id", F.col("text").contains("http").alias("has_url"), F.col("text").rlike("[0-9]{3}").alias("has_number"), F.col("lang").isin("en", "fr").alias("western"))


@query("SELECT doc_id, lang, quality, label FROM documents JOIN labels USING (doc_id) JOIN embeddings ON doc_id = vec_id")
def op_join_inner(spark, d):
    docs, labels, vecs = tables(spark, d, "documents", "labels", "embeddings")
    return docs.join(labels, "doc_id").join(vecs, F.col("doc_id") == F.col("vec_id")).select("doc_id", "lang", "quality", "label")


@query("SELECT doc_id, coalesce(toxic, -1) AS toxic FROM documents LEFT JOIN labels USING (doc_id)")
def op_join_left(spark, d):
    docs, labels = tables(spark, d, "documents", "labels")
    return docs.join(labels, "doc_id", "left").select("doc_id", F.coalesce("toxic", F.lit(-1)).alias("toxic"))


@query("SELECT coalesce(doc_id, vec_id) AS id, doc_id IS NULL AS no_text, vec_id IS NULL AS no_vector FROM documents FULL JOIN embeddings ON doc_id = vec_id")
def op_join_full(spark, d):
    docs, vecs = tables(spark, d, "documents", "embeddings")
    return docs.select("doc_id").join(vecs.select("vec_id"), F.col("doc_id") == F.col("vec_id"), "full").select(F.coalesce("doc_id", "vec_id").alias("id"), F.col("doc_id").isNull().alias("no_text"), F.col("vec_id").isNull().alias("no_vector"))


@query("SELECT doc_id FROM documents WHERE doc_id IN (SELECT doc_id FROM labels WHERE quality = 1)")
def op_join_semi(spark, d):
    docs, labels = tables(spark, d, "documents", "labels")
    return docs.join(labels.where("quality = 1"), "doc_id", "left_semi").select("doc_id")


@query("SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
def op_join_anti(spark, d):
    docs, labels = tables(spark, d, "documents", "labels")
    return docs.join(labels, "doc_id", "left_anti").select("doc_id")


@query("SELECT a.r_name AS a, b.r_name AS b FROM region a JOIN region b ON a.r_regionkey < b.r_regionkey")
def op_join_theta_pairs(spark, d):
    r = table(spark, d, "region")
    return r.select(F.col("r_name").alias("a"), F.col("r_regionkey").alias("ka")).join(F.broadcast(r.select(F.col("r_name").alias("b"), F.col("r_regionkey").alias("kb"))), F.col("ka") < F.col("kb")).select("a", "b")


@query("SELECT bucket, count(*) AS n FROM documents JOIN (VALUES ('short', 0, 500), ('middle', 500, 2000), ('long', 2000, 1000000000)) t(bucket, lo, hi) ON n_chars >= lo AND n_chars < hi GROUP BY bucket")
def op_join_range_buckets(spark, d):
    bounds = spark.createDataFrame([("short", 0, 500), ("middle", 500, 2000), ("long", 2000, 10**9)], "bucket string, lo long, hi long")
    return table(spark, d, "documents").select("n_chars").join(F.broadcast(bounds), (F.col("n_chars") >= F.col("lo")) & (F.col("n_chars") < F.col("hi"))).groupBy("bucket").agg(n())


@query("""SELECT event_id, last_value(CASE WHEN event_type = (SELECT min(event_type) FROM events) THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS as_of FROM events""")
def op_join_asof_last(spark, d):
    """The latest event of a given type at each event, of the same user: a window over the union, not a join."""
    e = table(spark, d, "events")
    kind = e.agg(F.min("event_type").alias("kind"))
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    return e.crossJoin(F.broadcast(kind)).select("event_id", F.last(F.when(F.col("event_type") == F.col("kind"), F.col("event_id")), ignorenulls=True).over(w).alias("as_of"))


@query("SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR WHERE a.event_type <> b.event_type")
def op_join_interval_events(spark, d):
    e = table(spark, d, "events").select("event_id", "user_id", "ts", "event_type")
    a, b = e.alias("a"), e.alias("b")
    on = (F.col("a.user_id") == F.col("b.user_id")) & (F.col("b.ts") > F.col("a.ts")) & (F.col("b.ts") <= F.col("a.ts") + F.expr("INTERVAL 1 HOUR"))
    return a.join(b, on).where("a.event_type <> b.event_type").select(F.col("a.event_id").alias("a"), F.col("b.event_id").alias("b"))


@query("SELECT r_name, lang, count(*) AS n FROM region CROSS JOIN (SELECT DISTINCT lang FROM documents) GROUP BY r_name, lang")
def op_cross_broadcast(spark, d):
    r, docs = tables(spark, d, "region", "documents")
    return r.crossJoin(F.broadcast(docs.select("lang").distinct())).groupBy("r_name", "lang").agg(n())


@query("SELECT lang, source, count(*) AS n, sum(n_chars)::BIGINT AS chars FROM documents GROUP BY lang, source")
def op_agg_hash(spark, d):
    return table(spark, d, "documents").groupBy("lang", "source").agg(n(), F.sum("n_chars").alias("chars"))


@query("SELECT lang, count(DISTINCT source) AS sources, count(DISTINCT text) AS texts FROM documents GROUP BY lang")
def op_agg_distinct(spark, d):
    return table(spark, d, "documents").groupBy("lang").agg(F.count_distinct("source").alias("sources"), F.count_distinct("text").alias("texts"))


@query()
def op_agg_approx_distinct(spark, d):
    return table(spark, d, "documents").groupBy("lang").agg(F.approx_count_distinct("text").alias("approx"), F.hll_sketch_estimate(F.hll_sketch_agg("text")).alias("hll"))


@query()
def op_agg_quantile_sketch(spark, d):
    return table(spark, d, "documents").groupBy("lang").agg(F.percentile_approx("n_chars", [0.1, 0.5, 0.9]).alias("q"))


@query("SELECT l_returnflag, round(avg(l_quantity), 6) AS mean, round(var_pop(l_quantity), 4) AS var, round(corr(l_quantity, l_extendedprice), 6) AS rho FROM lineitem GROUP BY l_returnflag")
def op_agg_moments(spark, d):
    q, p = F.col("l_quantity").cast("double"), F.col("l_extendedprice").cast("double")
    return table(spark, d, "lineitem").groupBy("l_returnflag").agg(F.round(F.avg(q), 6).alias("mean"), F.round(F.var_pop(q), 4).alias("var"), F.round(F.corr(q, p), 6).alias("rho"))


@query("SELECT l_returnflag, round(regr_slope(l_extendedprice::DOUBLE, l_quantity::DOUBLE), 4) AS slope FROM lineitem GROUP BY l_returnflag")
def op_agg_regression(spark, d):
    return table(spark, d, "lineitem").groupBy("l_returnflag").agg(F.round(F.regr_slope(F.col("l_extendedprice").cast("double"), F.col("l_quantity").cast("double")), 4).alias("slope"))


@query("SELECT source, arg_min(doc_id, (n_chars, doc_id)) AS shortest, arg_max(doc_id, (n_chars, doc_id)) AS longest FROM documents GROUP BY source")
def op_agg_min_by(spark, d):
    return table(spark, d, "documents").groupBy("source").agg(F.min_by("doc_id", F.struct("n_chars", "doc_id")).alias("shortest"), F.max_by("doc_id", F.struct("n_chars", "doc_id")).alias("longest"))


@query("SELECT lang, source, count(*) AS n FROM documents GROUP BY GROUPING SETS ((lang, source), (lang), ())")
def op_grouping_sets(spark, d):
    return table(spark, d, "documents").groupingSets([["lang", "source"], ["lang"], []], "lang", "source").agg(n())


@query("SELECT lang, source, grouping_id(lang, source)::BIGINT AS gid, count(*) AS n FROM documents GROUP BY CUBE (lang, source)")
def op_cube_lang_source(spark, d):
    return table(spark, d, "documents").cube("lang", "source").agg(F.grouping_id().cast("long").alias("gid"), n())


@query("SELECT r_name, n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)")
def op_rollup_region_nation(spark, d):
    c, na, r = tables(spark, d, "customer", "nation", "region")
    return c.join(F.broadcast(na), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(r), F.col("n_regionkey") == F.col("r_regionkey")).rollup("r_name", "n_name").agg(n())


@query("SELECT doc_id, row_number() OVER w AS rn, rank() OVER (PARTITION BY source ORDER BY n_chars) AS rk, dense_rank() OVER (PARTITION BY source ORDER BY n_chars) AS dr FROM documents WINDOW w AS (PARTITION BY source ORDER BY n_chars, doc_id)")
def op_window_rank(spark, d):
    w, t = Window.partitionBy("source").orderBy("n_chars", "doc_id"), Window.partitionBy("source").orderBy("n_chars")
    return table(spark, d, "documents").select("doc_id", F.row_number().over(w).alias("rn"), F.rank().over(t).alias("rk"), F.dense_rank().over(t).alias("dr"))


@query("SELECT doc_id, sum(n_chars) OVER (PARTITION BY source ORDER BY doc_id ROWS UNBOUNDED PRECEDING)::BIGINT AS run FROM documents")
def op_window_running(spark, d):
    w = Window.partitionBy("source").orderBy("doc_id").rowsBetween(Window.unboundedPreceding, 0)
    return table(spark, d, "documents").select("doc_id", F.sum("n_chars").over(w).alias("run"))


@query("SELECT doc_id, lag(n_chars) OVER w AS before, lead(n_chars) OVER w AS after FROM documents WINDOW w AS (PARTITION BY source ORDER BY doc_id)")
def op_window_lag(spark, d):
    w = Window.partitionBy("source").orderBy("doc_id")
    return table(spark, d, "documents").select("doc_id", F.lag("n_chars").over(w).alias("before"), F.lead("n_chars").over(w).alias("after"))


@query("SELECT doc_id, count(*) OVER (PARTITION BY source ORDER BY n_chars RANGE BETWEEN 100 PRECEDING AND 100 FOLLOWING) AS near FROM documents")
def op_window_range_frame(spark, d):
    w = Window.partitionBy("source").orderBy("n_chars").rangeBetween(-100, 100)
    return table(spark, d, "documents").select("doc_id", F.count(F.lit(1)).over(w).alias("near"))


@query("SELECT doc_id, ntile(4) OVER (PARTITION BY source ORDER BY n_chars, doc_id) AS quarter FROM documents")
def op_window_ntile(spark, d):
    return table(spark, d, "documents").select("doc_id", F.ntile(4).over(Window.partitionBy("source").orderBy("n_chars", "doc_id")).alias("quarter"))


@query("SELECT doc_id, n_chars FROM documents ORDER BY n_chars DESC, doc_id LIMIT 20")
def op_topk_global(spark, d):
    return table(spark, d, "documents").select("doc_id", "n_chars").orderBy(F.desc("n_chars"), "doc_id").limit(20)


@query("SELECT source, doc_id FROM documents QUALIFY row_number() OVER (PARTITION BY source ORDER BY n_chars DESC, doc_id) <= 3")
def op_topk_group(spark, d):
    w = Window.partitionBy("source").orderBy(F.desc("n_chars"), "doc_id")
    return table(spark, d, "documents").select("source", "doc_id", F.row_number().over(w).alias("rn")).where("rn <= 3").drop("rn")


@query("SELECT doc_id FROM documents WHERE lang = 'de' UNION SELECT doc_id FROM labels")
def op_union(spark, d):
    docs, labels = tables(spark, d, "documents", "labels")
    return docs.where("lang = 'de'").select("doc_id").unionByName(labels.select("doc_id")).distinct()


@query("SELECT doc_id FROM documents WHERE lang = 'en' INTERSECT SELECT doc_id FROM labels WHERE toxic = 1")
def op_intersect(spark, d):
    docs, labels = tables(spark, d, "documents", "labels")
    return docs.where("lang = 'en'").select("doc_id").intersect(labels.where("toxic = 1").select("doc_id"))


@query("SELECT doc_id FROM documents EXCEPT SELECT doc_id FROM labels")
def op_except(spark, d):
    docs, labels = tables(spark, d, "documents", "labels")
    return docs.select("doc_id").exceptAll(labels.select("doc_id")).distinct()


@query("SELECT doc_id, md5(text) AS digest, length(replace(text, ' ', '')) AS solid, upper(lang) || '-' || source AS tag, levenshtein(lang, source) AS edits FROM documents")
def op_string_fns(spark, d):
    return table(spark, d, "documents").select("doc_id", F.md5(F.col("text").cast("binary")).alias("digest"), F.length(F.replace("text", F.lit(" "), F.lit(""))).cast("long").alias("solid"), F.concat(F.upper("lang"), F.lit("-"), "source").alias("tag"), F.levenshtein("lang", "source").cast("long").alias("edits"))


@query("SELECT event_id, epoch_us(date_trunc('hour', ts)) AS hour_us, dayofmonth(ts) AS dom FROM events")
def op_date_fns(spark, d):
    return table(spark, d, "events").select("event_id", F.unix_micros(F.date_trunc("hour", F.col("ts").cast("timestamp"))).alias("hour_us"), F.dayofmonth("ts").alias("dom"))


@query("SELECT event_id, round(ln(1 + abs(value)), 6) AS l, round(sqrt(abs(value)), 6) AS s, round(1 / (1 + exp(-value / 100)), 6) AS g FROM events")
def op_math_fns(spark, d):
    v = F.col("value")
    return table(spark, d, "events").select("event_id", F.round(F.log1p(F.abs(v)), 6).alias("l"), F.round(F.sqrt(F.abs(v)), 6).alias("s"), F.round(1 / (1 + F.exp(-v / 100)), 6).alias("g"))


@query("SELECT vec_id, round(list_sum(list_transform(embedding::DOUBLE[], lambda x: x * x)), 5) AS sq, len(list_filter(embedding, lambda x: x > 0))::INT AS positive FROM embeddings")
def op_array_fns(spark, d):
    e = F.col("embedding").cast("array<double>")
    return table(spark, d, "embeddings").select("vec_id", F.round(F.aggregate(F.transform(e, lambda x: x * x), F.lit(0.0), lambda a, x: a + x), 5).alias("sq"), F.size(F.filter("embedding", lambda x: x > 0)).alias("positive"))


@query("SELECT source, list_aggregate(list(lang || '=' || n ORDER BY lang), 'string_agg', ',') AS histogram FROM (SELECT source, lang, count(*) AS n FROM documents GROUP BY source, lang) GROUP BY source")
def op_map_histogram(spark, d):
    by = table(spark, d, "documents").groupBy("source", "lang").agg(n())
    m = by.groupBy("source").agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("lang", "n")))).alias("m"))
    return m.select("source", F.array_join(F.transform(F.map_entries("m"), lambda e: F.concat(e["key"], F.lit("="), e["value"].cast("string"))), ",").alias("histogram"))


@query("SELECT event_id, (props::JSON ->> '$.k')::BIGINT AS k FROM events")
def op_json_props(spark, d):
    return table(spark, d, "events").select("event_id", F.from_json("props", "k BIGINT")["k"].alias("k"))


@query()
def op_html_text(spark, d):
    return table(spark, d, "pages").select("page_id", strip_html("html").alias("text")).select("page_id", n_tokens("text").alias("n_tokens"), F.md5(F.col("text").cast("binary")).alias("digest"))


@query("SELECT conv_id, count(*) AS turns, md5(string_agg(role || ': ' || text, chr(10) ORDER BY turn, role, text)) AS digest FROM conversations GROUP BY conv_id")
def op_fold_turns(spark, d):
    turns = F.array_sort(F.collect_list(F.struct("turn", "role", "text")))
    folded = table(spark, d, "conversations").groupBy("conv_id").agg(n().alias("turns"), turns.alias("t"))
    return folded.select("conv_id", "turns", F.md5(F.array_join(F.transform("t", lambda x: F.concat(x["role"], F.lit(": "), x["text"])), "\n").cast("binary")).alias("digest"))


@query("""SELECT n_name, round(sum(l_extendedprice::DOUBLE * (1 - l_discount::DOUBLE)), 2) AS revenue FROM customer JOIN orders ON c_custkey = o_custkey JOIN lineitem ON l_orderkey = o_orderkey
 JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY n_name""")
def op_star_join_revenue(spark, d):
    c, o, li, na, r = tables(spark, d, "customer", "orders", "lineitem", "nation", "region")
    geo = na.join(F.broadcast(r), F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", "n_name")
    rows = li.join(o, F.col("l_orderkey") == F.col("o_orderkey")).join(c, F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(geo), F.col("c_nationkey") == F.col("n_nationkey"))
    return rows.groupBy("n_name").agg(F.round(F.sum(F.col("l_extendedprice").cast("double") * (1 - F.col("l_discount").cast("double"))), 2).alias("revenue"))


def _events(spark, d):
    return table(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))


@query("SELECT epoch_us(time_bucket(INTERVAL 1 DAY, ts)) AS start_us, event_type, count(*) AS n, round(sum(value), 3) AS v FROM events GROUP BY ALL")
def op_tumbling(spark, d):
    return streams.windows(_events(spark, d), "1 day").select(F.unix_micros("start").alias("start_us"), "event_type", "n", F.round("v", 3).alias("v"))


@query("SELECT epoch_us(time_bucket(INTERVAL 1 DAY, ts) - INTERVAL 1 DAY * i) AS start_us, event_type, count(*) AS n, round(sum(value), 3) AS v FROM events CROSS JOIN (VALUES (0), (1)) t(i) GROUP BY ALL")
def op_sliding(spark, d):
    return streams.windows(_events(spark, d), "2 days", "1 day").select(F.unix_micros("start").alias("start_us"), "event_type", "n", F.round("v", 3).alias("v"))


@query("""SELECT user_id, epoch_us(min(ts)) AS start_us, epoch_us(max(ts) + INTERVAL 6 HOUR) AS stop_us, count(*) AS n FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS s FROM
 (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) <= INTERVAL 6 HOUR THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, s""")
def op_session(spark, d):
    return streams.sessions(_events(spark, d), "6 hours").select("user_id", F.unix_micros("start").alias("start_us"), F.unix_micros("stop").alias("stop_us"), "n")


def _as_files(df: DataFrame, parts: int) -> str:
    path = f"{shared_root(df.sparkSession)}/source-{uuid.uuid4().hex}"
    df.repartition(parts).write.parquet(path)
    return path


@query()
def op_stream_assign(spark, d):
    c = corpus_vec(spark, d).select("doc_id", "emb")
    centres = lloyd.fit(c, 6, 3)
    src = streams.file_stream(spark, _as_files(c, 3), c.schema)
    return streams.replay(streams.assign_stream(src, centres))


@query()
def op_stream_dedup(spark, d):
    e = _events(spark, d).select("event_id", "ts", "event_type")
    twice = e.unionByName(e)
    return streams.replay(streams.first_only(streams.file_stream(spark, _as_files(twice, 2), e.schema), ["event_id"], "40 days")).groupBy("event_type").agg(n())


@query()
def op_stream_windows(spark, d):
    e = _events(spark, d).select("ts", "event_type", "value")
    return streams.replay(streams.windows(streams.file_stream(spark, _as_files(e, 3), e.schema), "1 day"), "complete")


@query()
def op_stream_stateful(spark, d):
    c = corpus_vec(spark, d).select("doc_id", F.col("k").cast("int").alias("k"), "n_tokens")
    out = streams.replay(streams.running_quota(streams.file_stream(spark, _as_files(c, 3), c.schema)), "update")
    return out.groupBy("k").agg(F.max("n").alias("n"), F.max("tokens").alias("tokens"))


@query("SELECT vec_id, round(list_dot_product(embedding::DOUBLE[], embedding::DOUBLE[]), 5) AS sq FROM embeddings")
def op_udf_dot(spark, d):
    e = F.col("embedding").cast("array<double>")
    return table(spark, d, "embeddings").select("vec_id", F.round(vec_dot(e, e), 5).alias("sq"))


@query("SELECT source, round(entropy(lang) * ln(2), 6) + 0.0 AS entropy FROM documents GROUP BY source")
def op_udaf_entropy(spark, d):
    return table(spark, d, "documents").groupBy("source").agg((F.round(entropy_of("lang"), 6) + F.lit(0.0)).alias("entropy"))


@query("SELECT item_id, count(*) AS n FROM (SELECT item_id, unnest(range(0, greatest(len(regexp_extract_all(text, '\\S+')) - 4, 1))) AS i FROM benchmark) GROUP BY item_id")
def op_udtf_shingles(spark, d):
    return table(spark, d, "benchmark").lateralJoin(Shingles(F.col("text").outer(), F.lit(5))).groupBy("item_id").agg(n())


@query("SELECT source, lang, count(*) AS n FROM documents GROUP BY source, lang")
def op_sink_roundtrip(spark, d):
    path = f"{shared_root(spark)}/sink-{uuid.uuid4().hex}"
    write_partitioned(table(spark, d, "documents").select("doc_id", "source", "lang"), path, "lang")
    return spark.read.schema("doc_id long, source string, lang string").parquet(path).groupBy("source", "lang").agg(n())


@query("SELECT source, count(*) AS docs, floor(count(*) * 0.3)::BIGINT AS wanted FROM documents GROUP BY source")
def op_sql_surface(spark, d):
    from curator.sqlsurface import mix_of

    install(spark, d)
    return mix_of(spark, 0.3)


@query("SELECT vec_id, round(list_dot_product(embedding::DOUBLE[], list_reverse(embedding::DOUBLE[])), 5) + 0.0 AS x FROM embeddings")
def op_vector_codegen(spark, d):
    e = stash(table(spark, d, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("e")), "vectors")
    return e.select("vec_id", (F.round(dot(F.col("e"), F.reverse("e")), 5) + F.lit(0.0)).alias("x"))
