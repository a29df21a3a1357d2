"""Registered queries of the operators around the methods: one for each, with a DuckDB oracle wherever SQL can say it."""

from __future__ import annotations

import uuid

from pyspark.sql import Window as W
from pyspark.sql import functions as F

from lexbridge.sources.stage import shared_folder
from lexbridge.functions import udfs
from lexbridge.sources.tables import table

QUERIES, ORACLES = {}, {}


def query(oracle: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if oracle is not None:
            ORACLES[f.__name__] = oracle
        return f

    return add


def sql(name: str, spark_sql: str, duck_sql: str | None = None, tables: str = "documents labels events orders lineitem customer nation region part supplier embeddings pages benchmark conversations") -> None:
    """A query whose Spark form is SQL text over temporary views; the oracle is the same text unless another is given."""

    def run(spark, sf_dir):
        for t in tables.split():
            if t in spark_sql:
                table(spark, sf_dir, t).createOrReplaceTempView(t)
        return spark.sql(spark_sql)

    run.__name__ = name
    QUERIES[name] = run
    ORACLES[name] = duck_sql or spark_sql


def _folder(spark) -> str:
    sc = spark.sparkContext
    base = shared_folder(spark)
    return f"{base.rstrip('/')}/io-{uuid.uuid4().hex[:12]}"


# ---- scans and sinks


@query("SELECT doc_id, lang FROM documents WHERE n_chars > 2000 AND lang = 'en'")
def op_scan_pushdown(spark, sf_dir):
    return table(spark, sf_dir, "documents").where("n_chars > 2000 and lang = 'en'").select("doc_id", "lang")


def _round_trip(fmt: str, **options):
    def run(spark, sf_dir):
        path = _folder(spark)
        df = table(spark, sf_dir, "documents").select("doc_id", "lang", "source", "n_chars")
        df.write.format(fmt).options(**options).save(path)
        return spark.read.schema(df.schema).format(fmt).options(**options).load(path)

    return run


for _fmt, _opt in (("json", {}), ("csv", {"header": "true"}), ("orc", {})):
    QUERIES[f"op_scan_{_fmt}"] = _round_trip(_fmt, **_opt)
    ORACLES[f"op_scan_{_fmt}"] = "SELECT doc_id, lang, source, n_chars FROM documents"


@query("SELECT lang AS value, count(*) AS n FROM documents GROUP BY lang")
def op_scan_text(spark, sf_dir):
    path = _folder(spark)
    table(spark, sf_dir, "documents").select("lang").write.text(path)
    return spark.read.text(path).groupBy("value").agg(F.count("*").alias("n"))


@query("SELECT doc_id, source, lang FROM documents WHERE lang = 'de'")
def op_sink_partitioned(spark, sf_dir):
    path = _folder(spark)
    table(spark, sf_dir, "documents").select("doc_id", "source", "lang").write.partitionBy("lang").parquet(path)
    return spark.read.parquet(path).where("lang = 'de'").select("doc_id", "source", "lang")


@query("SELECT lang, count(*) AS n FROM (SELECT doc_id, CASE WHEN lang = 'de' THEN 'de' ELSE lang END AS lang FROM documents WHERE NOT (lang = 'de' AND doc_id % 2 = 1)) GROUP BY lang")
def op_sink_dynamic_overwrite(spark, sf_dir):
    """Only the rewritten partition changes."""
    path = _folder(spark)
    docs = table(spark, sf_dir, "documents").select("doc_id", "lang")
    docs.write.partitionBy("lang").parquet(path)
    docs.where("lang = 'de' and doc_id % 2 = 0").write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("lang").parquet(path)
    return spark.read.parquet(path).groupBy("lang").agg(F.count("*").alias("n"))


# ---- projection, filter, joins

sql("op_projection", "SELECT o_orderkey, o_totalprice * 2 AS twice, upper(o_orderstatus) AS status FROM orders")
sql("op_filter", "SELECT o_orderkey FROM orders WHERE o_totalprice BETWEEN 1000 AND 50000 AND o_orderpriority LIKE '%URGENT' AND o_orderstatus IN ('O', 'F')")
sql("op_join_inner", "SELECT n_name, count(*) AS orders FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name")
sql("op_join_left", "SELECT d.doc_id, coalesce(l.toxic, -1) AS toxic FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id")
sql("op_join_full", "SELECT coalesce(a.k, b.k) AS k, coalesce(a.n, 0) AS n_a, coalesce(b.n, 0) AS n_b FROM (SELECT o_custkey AS k, count(*) AS n FROM orders GROUP BY o_custkey) a FULL OUTER JOIN (SELECT c_custkey AS k, count(*) AS n FROM customer WHERE c_acctbal > 0 GROUP BY c_custkey) b ON a.k = b.k")
sql("op_join_semi", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 100000)")
sql("op_join_anti", "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")
sql("op_join_cross_pairs", "SELECT a.r_name AS src, b.r_name AS tgt FROM region a CROSS JOIN region b WHERE a.r_name <> b.r_name")
sql("op_join_null_safe", "SELECT a.doc_id, b.n FROM (SELECT d.doc_id, l.toxic FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id) a JOIN (SELECT toxic, count(*) AS n FROM (SELECT d.doc_id, l.toxic FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id) GROUP BY toxic) b ON a.toxic <=> b.toxic",
    "SELECT a.doc_id, b.n FROM (SELECT d.doc_id, l.toxic FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id) a JOIN (SELECT toxic, count(*) AS n FROM (SELECT d.doc_id, l.toxic FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id) GROUP BY toxic) b ON a.toxic IS NOT DISTINCT FROM b.toxic")
sql("op_join_range", "SELECT b.lo, count(*) AS n FROM lineitem JOIN (SELECT 0 AS lo, 10000 AS hi UNION ALL SELECT 10000, 30000 UNION ALL SELECT 30000, 1000000) b ON l_extendedprice >= b.lo AND l_extendedprice < b.hi GROUP BY b.lo")
sql("op_join_lateral", "SELECT c.c_custkey, t.o_orderkey, t.o_totalprice FROM customer c JOIN LATERAL (SELECT o_orderkey, o_totalprice FROM orders WHERE o_custkey = c.c_custkey ORDER BY o_totalprice DESC, o_orderkey LIMIT 2) t ON true")


@query("""SELECT p.event_id, count(*) AS before FROM events p JOIN events v ON v.user_id = p.user_id AND v.ts < p.ts AND v.ts >= p.ts - INTERVAL 1 HOUR WHERE p.event_type = 'purchase' GROUP BY p.event_id""")
def op_join_interval(spark, sf_dir):
    """Events of the same user in the hour before: each event is filed under its own hour and the next, so the range becomes an equi join."""
    e = table(spark, sf_dir, "events").select("event_id", "user_id", "event_type", F.col("ts").cast("timestamp").alias("ts"))
    hour = F.floor(F.unix_seconds("ts") / 3600)
    p = e.where("event_type = 'purchase'").select(F.col("event_id"), "user_id", F.col("ts").alias("at"), hour.alias("h"))
    v = e.select("user_id", "ts", F.explode(F.array(hour, hour + 1)).alias("h"))
    met = p.join(v, ["user_id", "h"]).where((F.col("ts") < F.col("at")) & (F.col("ts") >= F.col("at") - F.expr("INTERVAL 1 HOUR")))
    return met.groupBy("event_id").agg(F.count("*").alias("before"))


@query("""SELECT p.event_id, coalesce(v.event_id, -1) AS seen FROM (SELECT * FROM events WHERE event_type = 'purchase') p ASOF LEFT JOIN (SELECT user_id, ts, arg_max(event_id, event_id) AS event_id FROM events WHERE event_type = 'view' GROUP BY user_id, ts) v ON p.user_id = v.user_id AND p.ts >= v.ts""")
def op_join_asof(spark, sf_dir):
    """The last view at or before each purchase, in one pass: both kinds in one stream for each user, the last view carried forward."""
    e = table(spark, sf_dir, "events").where("event_type in ('view', 'purchase')").select("event_id", "user_id", "event_type", "ts")
    is_view = F.col("event_type") == "view"
    w = W.partitionBy("user_id").orderBy("ts", F.when(is_view, 0).otherwise(1), "event_id").rowsBetween(W.unboundedPreceding, 0)
    seen = e.withColumn("seen", F.last(F.when(is_view, F.col("event_id")), ignorenulls=True).over(w))
    return seen.where(~is_view).select("event_id", F.coalesce("seen", F.lit(-1)).alias("seen"))


@query("SELECT event_type, count(*) AS n, sum(u.k)::BIGINT AS total FROM events JOIN (SELECT user_id, count(*) AS k FROM events GROUP BY user_id) u USING (user_id) GROUP BY event_type")
def op_join_salted(spark, sf_dir):
    """A join whose hot keys are spread: the large side takes a salt, the small side is repeated for each."""
    e = table(spark, sf_dir, "events").select("event_id", "user_id", "event_type").withColumn("salt", F.pmod(F.xxhash64("event_id"), F.lit(8)))
    u = e.groupBy("user_id").agg(F.count("*").alias("k")).withColumn("salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(7).cast("long"))))
    return e.join(u, ["user_id", "salt"]).groupBy("event_type").agg(F.count("*").alias("n"), F.sum("k").alias("total"))


# ---- aggregation


@query("SELECT l_returnflag, l_linestatus, count(*) AS n, sum(l_quantity) AS quantity, avg(l_discount) AS discount, min(l_shipdate) AS first_ship, arg_max(l_orderkey, l_extendedprice) AS dearest FROM lineitem GROUP BY l_returnflag, l_linestatus")
def op_aggregate(spark, sf_dir):
    """Of rows of one greatest price the least key is told, which the oracle meets first in a table in order of its key."""
    dearest = F.max_by("l_orderkey", F.struct("l_extendedprice", -F.col("l_orderkey")))
    lines = table(spark, sf_dir, "lineitem").groupBy("l_returnflag", "l_linestatus")
    return lines.agg(F.count("*").alias("n"), F.sum("l_quantity").alias("quantity"), F.avg("l_discount").alias("discount"), F.min("l_shipdate").alias("first_ship"), dearest.alias("dearest"))


sql("op_aggregate_stats", "SELECT event_type, stddev_samp(value) AS sd, corr(value, user_id) AS r, count_if(value > 50) AS high FROM events GROUP BY event_type",
    "SELECT event_type, stddev_samp(value) AS sd, corr(value, user_id) AS r, count(*) FILTER (WHERE value > 50) AS high FROM events GROUP BY event_type")
sql("op_aggregate_distinct", "SELECT lang, count(DISTINCT source) AS sources, count(DISTINCT n_chars) AS sizes FROM documents GROUP BY lang")
sql("op_rollup", "SELECT lang, source, count(*) AS n, grouping(source) AS g FROM documents GROUP BY ROLLUP(lang, source)")
sql("op_cube", "SELECT coalesce(quality, -1) AS quality, coalesce(toxic, -1) AS toxic, n FROM (SELECT quality, toxic, count(*) AS n FROM labels GROUP BY CUBE(quality, toxic)) t")
sql("op_grouping_sets", "SELECT event_type, coalesce(u, -1) AS u, n FROM (SELECT event_type, u, count(*) AS n FROM (SELECT event_type, user_id % 7 AS u FROM events) e GROUP BY GROUPING SETS ((event_type), (u), ())) t")


@query("SELECT source, count(*) FILTER (WHERE lang = 'en') AS en, count(*) FILTER (WHERE lang = 'de') AS de FROM documents WHERE lang IN ('en', 'de') GROUP BY source")
def op_pivot(spark, sf_dir):
    d = table(spark, sf_dir, "documents").where("lang in ('en', 'de')")
    return d.groupBy("source").pivot("lang", ["en", "de"]).agg(F.count(F.lit(1))).na.fill(0)


@query("SELECT doc_id, 'quality' AS kind, quality AS value FROM labels UNION ALL SELECT doc_id, 'toxic', toxic FROM labels")
def op_unpivot(spark, sf_dir):
    return table(spark, sf_dir, "labels").unpivot(["doc_id"], ["quality", "toxic"], "kind", "value")


@query()
def op_approximate(spark, sf_dir):
    """Sketches beside the exact figures: distinct users by HyperLogLog, a quantile by rank sketch."""
    e = table(spark, sf_dir, "events")
    return e.groupBy("event_type").agg(F.approx_count_distinct("user_id", 0.02).alias("users_about"), F.count_distinct("user_id").alias("users"), F.hll_sketch_estimate(F.hll_sketch_agg("user_id")).alias("users_hll"), F.percentile_approx("value", F.lit(0.5), F.lit(10_000)).alias("median_about"), F.percentile("value", F.lit(0.5)).alias("median"))


# ---- windows, order, sets, subqueries

sql("op_window_ranking", "SELECT o_orderkey, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, ntile(4) OVER (PARTITION BY o_custkey ORDER BY o_orderkey) AS q FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderkey)")
sql("op_window_distribution", "SELECT event_id, percent_rank() OVER w AS pr, cume_dist() OVER w AS cd FROM events WINDOW w AS (PARTITION BY event_type ORDER BY value, event_id)")
sql("op_window_analytic", "SELECT event_id, lag(value) OVER w AS before, lead(value) OVER w AS after, first_value(value) OVER w AS first FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)",
    'SELECT event_id, lag(value) OVER w AS before, lead(value) OVER w AS after, first_value(value) OVER w AS "first" FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)')
sql("op_window_rows", "SELECT event_id, sum(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS s3 FROM events")
sql("op_window_range", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 HOUR PRECEDING AND CURRENT ROW) AS hour FROM events", 'SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 HOUR PRECEDING AND CURRENT ROW) AS "hour" FROM events')
sql("op_top_k", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20")
sql("op_top_k_per_group", "SELECT o_custkey, o_orderkey FROM (SELECT o_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS r FROM orders) t WHERE r <= 3")
sql("op_limit_offset", "SELECT c_custkey FROM customer ORDER BY c_acctbal DESC, c_custkey LIMIT 10 OFFSET 5")
sql("op_union_all", "SELECT doc_id AS id, length(text) AS n FROM documents UNION ALL SELECT item_id, length(text) FROM benchmark")
sql("op_intersect", "SELECT c_nationkey AS k FROM customer INTERSECT SELECT s_nationkey FROM supplier")
sql("op_except_all", "SELECT c_nationkey AS k FROM customer EXCEPT ALL SELECT s_nationkey FROM supplier")
sql("op_subquery_scalar", "SELECT o_orderkey FROM orders WHERE o_totalprice > (SELECT avg(o_totalprice) FROM orders)")
sql("op_subquery_correlated", "SELECT o.o_orderkey FROM orders o WHERE o.o_totalprice = (SELECT max(i.o_totalprice) FROM orders i WHERE i.o_custkey = o.o_custkey)")


@query("SELECT doc_id FROM documents WHERE ('0x' || substr(md5(text || '|5'), 1, 8))::BIGINT % 10 < 3")
def op_sample_hashed(spark, sf_dir):
    """Three tenths of the texts by hash: alike on every run and engine, and equal texts stay together."""
    from lexbridge.sources.tables import hash_bucket

    return table(spark, sf_dir, "documents").where(hash_bucket(F.col("text"), 5, 10) < 3).select("doc_id")


@query()
def op_sample_stratified(spark, sf_dir):
    return table(spark, sf_dir, "documents").select("doc_id", "lang").sampleBy("lang", {"en": 0.1, "de": 0.5, "fr": 0.5, "es": 0.5}, seed=3)


# ---- functions

sql("op_fn_string", "SELECT doc_id, md5(text) AS h, levenshtein(lang, source) AS lev, length(regexp_replace(text, '[a-z]', '')) AS rest, concat_ws('-', lang, source) AS tag, translate(source, 'src', 'SRC') AS up FROM documents",
    "SELECT doc_id, md5(text) AS h, levenshtein(lang, source) AS lev, length(regexp_replace(text, '[a-z]', '', 'g')) AS rest, concat_ws('-', lang, source) AS tag, translate(source, 'src', 'SRC') AS up FROM documents")
sql("op_fn_date", "SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, date_format(o_orderdate, 'yyyy-MM') AS ym, datediff(date'1999-01-01', to_date(o_orderdate)) AS days FROM orders",
    "SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, strftime(o_orderdate, '%Y-%m') AS ym, datediff('day', o_orderdate::DATE, date '1999-01-01') AS days FROM orders")
sql("op_fn_math", "SELECT event_id, ln(1 + abs(value)) AS l, exp(-abs(value) / 100) AS e, sqrt(abs(value)) AS s, sign(value) AS g, greatest(value, 10.0D) AS top, pmod(user_id, 7) AS p FROM events",
    "SELECT event_id, ln(1 + abs(value)) AS l, exp(-abs(value) / 100) AS e, sqrt(abs(value)) AS s, sign(value)::DOUBLE AS g, greatest(value, 10.0) AS top, user_id % 7 AS p FROM events")
sql("op_fn_array", "SELECT vec_id, aggregate(transform(embedding, x -> cast(x as double) * x), 0.0D, (a, x) -> a + x) AS norm2, size(filter(embedding, x -> x > 0)) AS pos, exists(embedding, x -> x > 0.4) AS big FROM embeddings",
    "SELECT vec_id, list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE)) AS norm2, len(list_filter(embedding, lambda x: x > 0))::INTEGER AS pos, len(list_filter(embedding, lambda x: x > 0.4)) > 0 AS big FROM embeddings")
sql("op_fn_json", "SELECT event_id, cast(get_json_object(props, '$.k') AS int) AS k FROM events", "SELECT event_id, (json_extract(props, '$.k'))::INTEGER AS k FROM events")
sql("op_fn_decimal", "SELECT l_returnflag, sum(cast(l_extendedprice AS decimal(18, 2)) * cast(1 - l_discount AS decimal(6, 2))) AS revenue FROM lineitem GROUP BY l_returnflag",
    "SELECT l_returnflag, sum(cast(l_extendedprice AS decimal(18, 2)) * cast(1 - l_discount AS decimal(6, 2))) AS revenue FROM lineitem GROUP BY l_returnflag")


@query("SELECT source, lang, count(*) AS n FROM documents GROUP BY ALL")
def op_fn_map(spark, sf_dir):
    """Counts packed in a map for each source and unpacked again."""
    d = table(spark, sf_dir, "documents").groupBy("source", "lang").agg(F.count("*").alias("n"))
    packed = d.groupBy("source").agg(F.map_from_entries(F.collect_list(F.struct("lang", "n"))).alias("m"))
    return packed.select("source", F.explode(F.map_filter("m", lambda k, v: v > 0)).alias("lang", "n"))


@query("SELECT event_id, (json_extract(props, '$.k'))::BIGINT AS k FROM events")
def op_fn_variant(spark, sf_dir):
    return table(spark, sf_dir, "events").select("event_id", F.variant_get(F.parse_json("props"), "$.k", "long").alias("k"))


@query("""SELECT a.vec_id, arg_max(b.vec_id, (round(list_dot_product(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 9), -b.vec_id)) AS nearest FROM embeddings a JOIN embeddings b ON a.label = b.label AND a.vec_id <> b.vec_id GROUP BY a.vec_id""")
def op_nearest_vector(spark, sf_dir):
    """The nearest other vector of the same label, by exact dot products."""
    e = table(spark, sf_dir, "embeddings").select("vec_id", "label", F.transform("embedding", lambda x: x.cast("double")).alias("v"))
    other = e.select(F.col("vec_id").alias("o"), "label", F.col("v").alias("w"))
    dot = F.aggregate(F.zip_with("v", "w", lambda x, y: x * y), F.lit(0.0), lambda a, x: a + x)
    met = e.join(other, "label").where("vec_id != o").withColumn("d", F.round(dot, 9))
    return met.groupBy("vec_id").agg(F.max_by("o", F.struct("d", -F.col("o"))).alias("nearest"))


# ---- user-defined forms


@query(r"SELECT sum((length(w) + 3) // 4)::BIGINT AS pieces, count(*) AS words FROM (SELECT unnest(regexp_extract_all(lower(text), '\p{L}+')) AS w FROM benchmark)")
def op_udf_pieces(spark, sf_dir):
    words = table(spark, sf_dir, "benchmark").select(F.explode(F.regexp_extract_all(F.lower("text"), F.lit(r"\p{L}+"), F.lit(0))).alias("w"))
    return words.agg(F.sum(F.size(udfs.pieces_plain("w", F.lit(4)))).alias("pieces"), F.count(udfs.piece_count("w")).alias("words"))


@query()
def op_udaf_td(spark, sf_dir):
    """The update rule run in sequence over each user's events, beside the closed form."""
    e = table(spark, sf_dir, "events").select("user_id", "event_id", "ts", F.when(F.col("value") > 50, 1).otherwise(-1).alias("label"))
    w = W.partitionBy("user_id")
    later = F.count("*").over(w) - F.row_number().over(w.orderBy("ts", "event_id"))
    e = e.withColumn("step", F.unix_micros(F.col("ts").cast("timestamp"))).withColumn("v", 0.05 * F.col("label") * F.pow(F.lit(0.95), later))
    seq = e.groupBy("user_id").agg(udfs.td_result(F.col("step"), F.col("event_id"), F.col("label"), F.lit(0.0), F.lit(0.95)).alias("sequential"))
    return seq.join(e.groupBy("user_id").agg(F.sum("v").alias("closed")), "user_id")


@query(r"""WITH w AS (SELECT page_id, regexp_extract_all(lower(url), '\p{L}+') AS words FROM pages),
t AS (SELECT page_id, generate_subscripts(words, 1) - 1 AS i, unnest(words) AS word FROM w),
c AS (SELECT a.page_id, a.i, a.word, b.i AS j, b.word AS other, row_number() OVER (PARTITION BY a.page_id, a.i ORDER BY round(length(b.word)::DOUBLE / (1 + abs(a.i - b.i)), 9) DESC, b.i) AS r FROM t a JOIN t b ON a.page_id = b.page_id AND a.i <> b.i WHERE length(a.word) >= 6),
two AS (SELECT page_id, i, word, min(j) AS j1, max(j) AS j2, arg_min(other, j) AS x1, arg_max(other, j) AS x2 FROM c WHERE r <= 2 GROUP BY ALL HAVING count(*) = 2)
SELECT page_id, CASE WHEN i < j1 THEN word ELSE x1 END AS w_a, CASE WHEN i < j1 THEN x1 WHEN i < j2 THEN word ELSE x2 END AS w_b, CASE WHEN i > j2 THEN word ELSE x2 END AS w_c, (i > j1)::INTEGER + (i > j2)::INTEGER AS slot FROM two""")
def op_udtf_facts(spark, sf_dir):
    """Facts of every page's address by a lateral table function: words of six letters or more, with the two others that weigh most by length over distance."""
    udfs.register(spark)
    words = F.regexp_extract_all(F.lower("url"), F.lit(r"\p{L}+"), F.lit(0))
    table(spark, sf_dir, "pages").select("page_id", words.alias("words")).createOrReplaceTempView("page_words")
    return spark.sql("SELECT t.page_id, f.* FROM (SELECT page_id, words, transform(words, (x, i) -> transform(words, (y, j) -> cast(length(y) AS double) / (1 + abs(i - j)))) AS m, filter(transform(words, (x, i) -> if(length(x) >= 6, i, -1)), i -> i >= 0) AS at FROM page_words) t, LATERAL facts_of_row(t.words, t.m, t.at) f")


@query("SELECT source, avg(n_chars) AS mean FROM documents GROUP BY source")
def op_group_map(spark, sf_dir):
    """Grouped map and co-grouped map stand in for small models of each group."""
    import pandas as pd

    d = table(spark, sf_dir, "documents").select("source", "n_chars")
    return d.groupBy("source").applyInPandas(lambda g: pd.DataFrame({"source": [g.source.iloc[0]], "mean": [g.n_chars.mean()]}), "source string, mean double")


@query("SELECT event_type, count(*) AS n FROM events WHERE value > 10.5 GROUP BY event_type")
def op_sql_parameters(spark, sf_dir):
    table(spark, sf_dir, "events").createOrReplaceTempView("events")
    return spark.sql("SELECT event_type, count(*) AS n FROM events WHERE value > :least GROUP BY event_type", args={"least": 10.5})


@query("SELECT lang, (sum(2 * toxic - 1))::DOUBLE / count(*) AS p FROM documents JOIN labels USING (doc_id) GROUP BY lang")
def op_sql_function(spark, sf_dir):
    udfs.register(spark)
    table(spark, sf_dir, "documents").createOrReplaceTempView("documents")
    table(spark, sf_dir, "labels").createOrReplaceTempView("labels")
    return spark.sql("SELECT lang, polarity(count_if(toxic = 1), count_if(toxic = 0)) AS p FROM documents JOIN labels USING (doc_id) GROUP BY lang")
