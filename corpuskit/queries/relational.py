"""Surrounding relational operators, scans, sinks and scalar functions over the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from corpuskit.operators import relational as R
from corpuskit.queries.registry import query, table
from corpuskit.session import new_path

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def both(name: str, text: str, duck: str | None = None) -> None:
    """A query that is the same SQL text on either side (or `duck` where a function has another name)."""

    def run(spark, d):
        for t in TABLES:
            if t in text:
                table(spark, d, t).createOrReplaceTempView(t)
        return spark.sql(text)

    query(name, duck or text)(run)


# scans and sinks


@query("scan_parquet_pruned", "SELECT doc_id, n_chars FROM documents WHERE source = 'src3'")
def scan_parquet_pruned(spark, d):
    return table(spark, d).filter("source = 'src3'").select("doc_id", "n_chars")


def _round_trip(spark, df: DataFrame, form: str, **options) -> DataFrame:
    path = new_path(spark, f"scan-{form}")
    df.write.options(**options).format(form).save(path)
    return spark.read.schema(df.schema).options(**options).format(form).load(path)


@query("scan_jsonl", "SELECT doc_id, source, md5(text) AS digest FROM documents")
def scan_jsonl(spark, d):
    rows = _round_trip(spark, table(spark, d).select("doc_id", "source", "text"), "json", compression="gzip")
    return rows.select("doc_id", "source", F.md5("text").alias("digest"))


@query("scan_csv", "SELECT n_nationkey, n_name, n_regionkey FROM nation")
def scan_csv(spark, d):
    return _round_trip(spark, table(spark, d, "nation").select("n_nationkey", "n_name", "n_regionkey"), "csv", header="true")


@query("scan_orc", "SELECT doc_id, lang, n_chars FROM documents")
def scan_orc(spark, d):
    return _round_trip(spark, table(spark, d).select("doc_id", "lang", "n_chars"), "orc")


@query("scan_text", "SELECT r_name AS value FROM region")
def scan_text(spark, d):
    return _round_trip(spark, table(spark, d, "region").select(F.col("r_name").alias("value")), "text")


@query("scan_binary")
def scan_binary(spark, d):
    path = new_path(spark, "scan-binary")
    table(spark, d, "region").write.parquet(path)
    return spark.read.format("binaryFile").option("pathGlobFilter", "*.parquet").load(path).select(F.regexp_extract("path", "[^/]*$", 0).alias("file"), "length")


@query("scan_many", "SELECT count(*) AS n_rows, 4 AS n_shards FROM documents")
def scan_many(spark, d):
    path = new_path(spark, "scan-many")
    table(spark, d).select("doc_id").withColumn("shard", F.pmod("doc_id", F.lit(4))).write.partitionBy("shard").parquet(path)
    rows = spark.read.parquet(path).select(F.regexp_extract("_metadata.file_path", "shard=(\\d+)", 1).alias("s"))
    return rows.agg(F.count("*").alias("n_rows"), F.count_distinct("s").cast("int").alias("n_shards"))


@query("sink_noop", "SELECT count(*) AS n_rows FROM documents")
def sink_noop(spark, d):
    """Every row is computed and none kept."""
    docs = table(spark, d)
    docs.write.format("noop").mode("overwrite").save()
    return docs.agg(F.count("*").alias("n_rows"))


@query("sink_partitioned", "SELECT source, count(*) AS n FROM documents WHERE source IN ('src1', 'src2') GROUP BY 1")
def sink_partitioned(spark, d):
    path = new_path(spark, "sink")
    table(spark, d).select("doc_id", "source").write.partitionBy("source").parquet(path)
    return spark.read.parquet(path).filter("source IN ('src1', 'src2')").groupBy("source").agg(F.count("*").alias("n"))


@query("sink_bucketed", "SELECT o_orderpriority, count(*) AS n_lines FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1")
def sink_bucketed(spark, d):
    for name, key, columns in (("lineitem", "l_orderkey", ["l_orderkey"]), ("orders", "o_orderkey", ["o_orderkey", "o_orderpriority"])):
        table(spark, d, name).select(*columns).write.bucketBy(4, key).sortBy(key).mode("overwrite").option("path", new_path(spark, f"bucketed-{name}")).saveAsTable(f"ck_{name}_bucketed")
    joined = spark.table("ck_lineitem_bucketed").join(spark.table("ck_orders_bucketed"), F.col("l_orderkey") == F.col("o_orderkey"))
    return joined.groupBy("o_orderpriority").agg(F.count("*").alias("n_lines"))


@query("sink_jsonl_zstd", "SELECT conv_id, turn, role FROM conversations")
def sink_jsonl_zstd(spark, d):
    return _round_trip(spark, table(spark, d, "conversations").select("conv_id", "turn", "role"), "json", compression="gzip")


# projections and filters

both("proj_expr", "SELECT l_orderkey, l_linenumber, round(l_extendedprice * (1 - l_discount), 4) AS revenue FROM lineitem")


@query("flt_conj", "SELECT p_partkey FROM part WHERE p_size BETWEEN 10 AND 20 AND p_retailprice > 950")
def flt_conj(spark, d):
    return table(spark, d, "part").filter(F.col("p_size").between(10, 20) & (F.col("p_retailprice") > 950)).select("p_partkey")


@query("flt_in_like", "SELECT p_partkey, p_type FROM part WHERE p_size IN (1, 5, 9) AND p_type LIKE '%E%'")
def flt_in_like(spark, d):
    return table(spark, d, "part").filter(F.col("p_size").isin(1, 5, 9) & F.col("p_type").like("%E%")).select("p_partkey", "p_type")


@query("flt_regex", "SELECT doc_id FROM documents WHERE regexp_matches(text, '[0-9]{3}-[0-9]{4}')")
def flt_regex(spark, d):
    return table(spark, d).filter(F.col("text").rlike("[0-9]{3}-[0-9]{4}")).select("doc_id")


@query("flt_null_safe", "SELECT d.doc_id FROM documents d LEFT JOIN labels l USING (doc_id) WHERE l.quality IS NOT DISTINCT FROM NULL")
def flt_null_safe(spark, d):
    return table(spark, d).join(table(spark, d, "labels"), "doc_id", "left").filter(F.col("quality").eqNullSafe(F.lit(None))).select("doc_id")


# joins


@query("join_hash_broadcast", "SELECT p_brand, count(*) AS n, round(sum(l_quantity), 2) AS quantity FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1")
def join_hash_broadcast(spark, d):
    part = table(spark, d, "part").select("p_partkey", "p_brand")  # left to the size-checked automatic broadcast
    return table(spark, d, "lineitem").join(part, F.col("l_partkey") == F.col("p_partkey")).groupBy("p_brand").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("quantity"))


_OL = "SELECT o_orderstatus, count(*) AS n FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1"


@query("join_shuffle_hash", _OL)
def join_shuffle_hash(spark, d):
    return table(spark, d, "lineitem").join(table(spark, d, "orders").hint("shuffle_hash"), F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderstatus").agg(F.count("*").alias("n"))


@query("join_sort_merge", _OL)
def join_sort_merge(spark, d):
    return table(spark, d, "lineitem").join(table(spark, d, "orders").hint("merge"), F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderstatus").agg(F.count("*").alias("n"))


@query("join_salted", _OL)
def join_salted(spark, d):
    lines = table(spark, d, "lineitem").select(F.col("l_orderkey").alias("k"), "l_linenumber")
    return R.salted_join(lines, table(spark, d, "orders").select(F.col("o_orderkey").alias("k"), "o_orderstatus"), "k", 4).groupBy("o_orderstatus").agg(F.count("*").alias("n"))


both("join_star", "SELECT r_name, n_name, count(*) AS n_lines, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY r_name, n_name")


@query("join_left", "SELECT doc_id, quality FROM documents LEFT JOIN labels USING (doc_id)")
def join_left(spark, d):
    return table(spark, d).select("doc_id").join(table(spark, d, "labels"), "doc_id", "left").select("doc_id", "quality")


@query("join_right", "SELECT doc_id, lang, quality FROM documents RIGHT JOIN labels USING (doc_id)")
def join_right(spark, d):
    return table(spark, d).join(table(spark, d, "labels"), "doc_id", "right").select("doc_id", "lang", "quality")


@query("join_full", "SELECT coalesce(a.doc_id, b.item_id) AS id, a.doc_id IS NOT NULL AS in_documents, b.item_id IS NOT NULL AS in_benchmark FROM (SELECT doc_id FROM documents WHERE doc_id % 3 = 0) a FULL JOIN benchmark b ON a.doc_id = b.item_id")
def join_full(spark, d):
    a, b = table(spark, d).filter("doc_id % 3 = 0").select("doc_id"), table(spark, d, "benchmark").select("item_id")
    return a.join(b, F.col("doc_id") == F.col("item_id"), "full").select(F.coalesce("doc_id", "item_id").alias("id"), F.col("doc_id").isNotNull().alias("in_documents"), F.col("item_id").isNotNull().alias("in_benchmark"))


@query("join_semi", "SELECT doc_id FROM documents WHERE doc_id IN (SELECT doc_id FROM labels)")
def join_semi(spark, d):
    return table(spark, d).join(table(spark, d, "labels"), "doc_id", "left_semi").select("doc_id")


@query("join_anti", "SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
def join_anti(spark, d):
    return table(spark, d).join(table(spark, d, "labels"), "doc_id", "left_anti").select("doc_id")


@query("join_grid", "SELECT s.source, l.lang, count(d.doc_id) AS n FROM (SELECT DISTINCT source FROM documents) s, (SELECT DISTINCT lang FROM documents) l LEFT JOIN documents d ON d.source = s.source AND d.lang = l.lang GROUP BY 1, 2")
def join_grid(spark, d):
    """Sources x languages with zeros: both lists are distinct names, so the grid is small."""
    docs = table(spark, d)
    grid = docs.select("source").distinct().crossJoin(docs.select("lang").distinct())
    return grid.join(docs.groupBy("source", "lang").agg(F.count("*").alias("n")), ["source", "lang"], "left").na.fill(0, ["n"])


@query("join_theta", "SELECT a.s_suppkey AS low, b.s_suppkey AS high FROM supplier a JOIN supplier b ON a.s_nationkey = b.s_nationkey AND a.s_acctbal < b.s_acctbal")
def join_theta(spark, d):
    s = table(spark, d, "supplier")
    a, b = s.select("s_nationkey", F.col("s_suppkey").alias("low"), F.col("s_acctbal").alias("x")), s.select("s_nationkey", F.col("s_suppkey").alias("high"), F.col("s_acctbal").alias("y"))
    return a.join(b, "s_nationkey").filter("x < y").select("low", "high")


@query("join_range", "SELECT band, count(*) AS n FROM documents JOIN (VALUES ('short', 0, 500), ('medium', 500, 2000), ('long', 2000, 1000000)) b(band, low, high) ON n_chars >= low AND n_chars < high GROUP BY 1")
def join_range(spark, d):
    bands = spark.createDataFrame([("short", 0, 500), ("medium", 500, 2000), ("long", 2000, 1_000_000)], "band string, low long, high long")
    return R.range_join(table(spark, d).select("n_chars"), bands, "n_chars", "low", "high", 5000).groupBy("band").agg(F.count("*").alias("n"))


_ERRORS = "SELECT a.event_id AS first_id, b.event_id AS second_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'error' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 5 MINUTE"


@query("join_interval", _ERRORS)
def join_interval(spark, d):
    e = table(spark, d, "events")
    a, b = e.filter("event_type = 'error'").select("user_id", "ts", F.col("event_id").alias("first_id")), e.select("user_id", "ts", F.col("event_id").alias("second_id"))
    return R.interval_join(a, b, "user_id", "ts", 300).select("first_id", "second_id")


@query("join_asof", "SELECT a.event_id, (SELECT max(b.ts) FROM events b WHERE b.user_id = a.user_id AND b.event_type <> 'purchase' AND b.ts < a.ts) AS ts_before FROM events a WHERE a.event_type = 'purchase'")
def join_asof(spark, d):
    e = table(spark, d, "events")
    return R.asof_join(e.filter("event_type = 'purchase'").select("user_id", "ts", "event_id"), e.filter("event_type != 'purchase'").select("user_id", "ts"), "user_id", "ts", []).select("event_id", "ts_before")


@query("join_self_pairs", "SELECT a.doc_id AS a, b.doc_id AS b FROM documents a JOIN documents b ON md5(a.text) = md5(b.text) AND a.doc_id < b.doc_id AND a.source = b.source")
def join_self_pairs(spark, d):
    k = table(spark, d).select("doc_id", "source", F.md5("text").alias("k"))
    return k.toDF("a", "source", "k").join(k.toDF("b", "source", "k"), ["source", "k"]).filter("a < b").select("a", "b")


# aggregates

both("agg_basic", "SELECT l_returnflag, l_linestatus, round(sum(l_quantity), 2) AS sum_qty, round(avg(l_extendedprice), 4) AS avg_price, count(*) AS n FROM lineitem GROUP BY l_returnflag, l_linestatus")
both("agg_distinct", "SELECT source, count(DISTINCT lang) AS n_langs FROM documents GROUP BY source")
both("agg_multi_distinct", "SELECT count(DISTINCT source) AS n_sources, count(DISTINCT lang) AS n_langs, count(DISTINCT n_chars) AS n_lengths FROM documents")
both("agg_filter_clause", "SELECT source, round(count(*) FILTER (WHERE n_chars < 300) / count(*), 6) AS short_share FROM documents GROUP BY source")
both("agg_having", "SELECT o_custkey, count(*) AS n FROM orders GROUP BY o_custkey HAVING count(*) > 15")
both("agg_min_by", "SELECT source, max(n_chars) AS longest, min_by(doc_id, doc_id) AS first_id FROM documents GROUP BY source")
both("agg_mode", "SELECT source, lang AS modal FROM (SELECT source, lang, row_number() OVER (PARTITION BY source ORDER BY n DESC, lang) AS place FROM (SELECT source, lang, count(*) AS n FROM documents GROUP BY source, lang)) WHERE place = 1")
both("agg_percentile", "SELECT lang, round(percentile(n_chars, 0.5), 4) AS p50, round(percentile(n_chars, 0.9), 4) AS p90 FROM documents GROUP BY lang", "SELECT lang, round(quantile_cont(n_chars, 0.5), 4) AS p50, round(quantile_cont(n_chars, 0.9), 4) AS p90 FROM documents GROUP BY lang")
both("agg_stddev_corr", "SELECT round(stddev_samp(l_quantity), 6) AS sd, round(corr(l_quantity, l_extendedprice), 6) AS r FROM lineitem")
both("agg_grouping_sets", "SELECT lang, source, count(*) AS n FROM documents GROUP BY GROUPING SETS ((lang, source), (lang), ())")
both("agg_cube", "SELECT lang, source, count(*) AS n, sum(n_chars) AS chars FROM documents GROUP BY CUBE (lang, source)", "SELECT lang, source, count(*) AS n, CAST(sum(n_chars) AS BIGINT) AS chars FROM documents GROUP BY CUBE (lang, source)")
both("agg_rollup", "SELECT source, lang, count(*) AS n FROM documents GROUP BY ROLLUP (source, lang)")


@query("agg_pivot", "SELECT source, count(*) FILTER (lang = 'de') AS de, count(*) FILTER (lang = 'en') AS en, count(*) FILTER (lang = 'es') AS es, count(*) FILTER (lang = 'fr') AS fr FROM documents GROUP BY 1")
def agg_pivot(spark, d):
    return table(spark, d).groupBy("source").pivot("lang", ["de", "en", "es", "fr"]).agg(F.count(F.lit(1))).na.fill(0)


@query("agg_unpivot", "SELECT source, lang, count(*) AS n FROM documents GROUP BY 1, 2")
def agg_unpivot(spark, d):
    return agg_pivot(spark, d).unpivot("source", ["de", "en", "es", "fr"], "lang", "n").filter("n > 0")


@query("agg_sort_based", "SELECT source, md5(string_agg(CAST(doc_id AS VARCHAR), ',' ORDER BY doc_id)) AS ids FROM documents GROUP BY 1")
def agg_sort_based(spark, d):
    return table(spark, d).groupBy("source").agg(F.md5(F.array_join(F.transform(F.sort_array(F.collect_list("doc_id")), lambda x: x.cast("string")), ",")).alias("ids"))


@query("agg_approx_distinct")
def agg_approx_distinct(spark, d):
    return table(spark, d).select(F.explode(F.split("text", "\\s+")).alias("w")).agg(F.approx_count_distinct("w", 0.01).alias("n_words"))


@query("agg_approx_pct")
def agg_approx_pct(spark, d):
    return table(spark, d).groupBy("lang").agg(F.percentile_approx("n_chars", [0.5, 0.9], 1000).alias("p"))


@query("agg_top_k_sketch")
def agg_top_k_sketch(spark, d):
    table(spark, d).createOrReplaceTempView("documents")
    return spark.sql("SELECT x.item AS word, x.count AS n FROM (SELECT explode(approx_top_k(w, 20, 10000)) AS x FROM (SELECT explode(split(text, ' ')) AS w FROM documents))")


@query("agg_sketch_merge")
def agg_sketch_merge(spark, d):
    per = table(spark, d).groupBy("source").agg(F.hll_sketch_agg(F.md5("text"), 12).alias("s"))
    return per.agg(F.hll_sketch_estimate(F.hll_union_agg("s")).alias("n_texts"))


# windows

both("win_row_number", "SELECT doc_id, row_number() OVER (PARTITION BY source ORDER BY n_chars DESC, doc_id) AS place FROM documents", "SELECT doc_id, CAST(row_number() OVER (PARTITION BY source ORDER BY n_chars DESC, doc_id) AS INTEGER) AS place FROM documents")
both("win_rank_dense", "SELECT p_partkey, rank() OVER w AS r, dense_rank() OVER w AS dr FROM part WINDOW w AS (PARTITION BY p_brand ORDER BY p_size)", "SELECT p_partkey, CAST(rank() OVER w AS INTEGER) AS r, CAST(dense_rank() OVER w AS INTEGER) AS dr FROM part WINDOW w AS (PARTITION BY p_brand ORDER BY p_size)")
both("win_ntile", "SELECT doc_id, ntile(4) OVER (PARTITION BY lang ORDER BY n_chars, doc_id) AS quarter FROM documents", "SELECT doc_id, CAST(ntile(4) OVER (PARTITION BY lang ORDER BY n_chars, doc_id) AS INTEGER) AS quarter FROM documents")
both("win_percent_rank_cume", "SELECT doc_id, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd FROM documents WINDOW w AS (PARTITION BY source ORDER BY n_chars)")
both("win_lag_lead", "SELECT event_id, lag(event_type) OVER w AS before, lead(event_type) OVER w AS after FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
both("win_first_last_nth", "SELECT event_id, first_value(event_id) OVER w AS f, nth_value(event_id, 2) OVER w AS second, last_value(event_id) OVER w AS l FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
both("win_running_rows", "SELECT o_orderkey, round(sum(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW), 2) AS running FROM orders")
both("win_moving_avg", "SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 6) AS moving FROM events")
both("win_range_interval", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL '1' HOUR PRECEDING AND CURRENT ROW) AS n FROM events")


@query("win_share", "SELECT source, n, round(n / sum(n) OVER (), 6) AS share FROM (SELECT source, count(*) AS n FROM documents GROUP BY 1)")
def win_share(spark, d):
    return R.share(table(spark, d).groupBy("source").agg(F.count("*").alias("n")), "n")


# order, top-k and sets

both("sort_multi", "SELECT doc_id, source FROM documents ORDER BY source DESC, n_chars, doc_id")
both("sort_nulls", "SELECT d.doc_id, l.quality FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id ORDER BY l.quality NULLS LAST, d.doc_id")


@query("sort_within")
def sort_within(spark, d):
    return table(spark, d).select("doc_id", "source").repartition(4, "source").sortWithinPartitions("source", "doc_id")


both("topk_global", "SELECT doc_id, n_chars FROM documents ORDER BY n_chars DESC, doc_id LIMIT 10")


@query("topk_per_group", "SELECT source, doc_id FROM documents QUALIFY row_number() OVER (PARTITION BY source ORDER BY n_chars DESC, doc_id) <= 3")
def topk_per_group(spark, d):
    w = Window.partitionBy("source").orderBy(F.desc("n_chars"), "doc_id")
    return table(spark, d).withColumn("r", F.row_number().over(w)).filter("r <= 3").select("source", "doc_id")


both("limit_offset", "SELECT doc_id FROM documents ORDER BY doc_id LIMIT 20 OFFSET 30")
_W = "SELECT n_chars AS v FROM documents WHERE source = 'src1'", "SELECT n_chars AS v FROM documents WHERE source = 'src2'"
for _name, _op in (("union_all", "UNION ALL"), ("union", "UNION"), ("intersect", "INTERSECT"), ("intersect_all", "INTERSECT ALL"), ("except", "EXCEPT"), ("except_all", "EXCEPT ALL")):
    both(f"set_{_name}", f"{_W[0]} {_op} {_W[1]}")

# subqueries

both("sub_scalar", "SELECT doc_id FROM documents WHERE n_chars > (SELECT avg(n_chars) FROM documents)")
both("sub_exists", "SELECT doc_id FROM documents d WHERE EXISTS (SELECT 1 FROM labels l WHERE l.doc_id = d.doc_id AND l.toxic = 1)")
both("sub_in", "SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders WHERE o_totalprice > 300000)")
both("sub_lateral", "SELECT n_name, t.n FROM nation, LATERAL (SELECT count(*) AS n FROM customer WHERE c_nationkey = n_nationkey) t")
_RUNNING = "WITH RECURSIVE m AS (SELECT CAST(row_number() OVER (ORDER BY source NULLS LAST) AS INT) AS k, c FROM (SELECT source, CAST(sum(n_chars) AS BIGINT) AS c FROM documents GROUP BY source)), t(n, s) AS (SELECT k, c FROM m WHERE k = 1 UNION ALL SELECT t.n + 1, t.s + m.c FROM t JOIN m ON m.k = t.n + 1) SELECT n, s FROM t"
both("sub_recursive", _RUNNING)

# functions

both("fn_case_trim_pad", "SELECT n_nationkey, lower(n_name) AS l, upper(trim(n_name)) AS u, lpad(n_name, 20, '.') AS p FROM nation")
both("fn_regex", "SELECT page_id, regexp_extract(url, '^([a-z]+)://', 1) AS scheme, regexp_replace(url, '[0-9]', '#') AS masked FROM pages", "SELECT page_id, regexp_extract(url, '^([a-z]+)://', 1) AS scheme, regexp_replace(url, '[0-9]', '#', 'g') AS masked FROM pages")
both("fn_split_slice", "SELECT doc_id, array_join(slice(split(text, ' '), 1, 3), '_') AS head FROM documents", "SELECT doc_id, array_to_string(string_split(text, ' ')[1:3], '_') AS head FROM documents")
both("fn_translate", "SELECT n_nationkey, translate(n_name, 'AEIOU', '12345') AS t FROM nation")
both("fn_hash", "SELECT doc_id, md5(text) AS m, sha2(text, 256) AS s FROM documents", "SELECT doc_id, md5(text) AS m, sha256(text) AS s FROM documents")
both("fn_length_bytes", "SELECT doc_id, length(text) AS chars, octet_length(text) AS bytes FROM documents", "SELECT doc_id, CAST(length(text) AS INTEGER) AS chars, CAST(strlen(text) AS INTEGER) AS bytes FROM documents")
both("fn_levenshtein", "SELECT a.n_name AS a, b.n_name AS b, levenshtein(a.n_name, b.n_name) AS dist FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey", "SELECT a.n_name AS a, b.n_name AS b, CAST(levenshtein(a.n_name, b.n_name) AS INTEGER) AS dist FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey")
both("fn_url", "SELECT page_id, parse_url(url, 'HOST') AS host FROM pages", "SELECT page_id, regexp_extract(url, '^[a-z]+://([^/:?#]+)', 1) AS host FROM pages")
both("fn_date_trunc", "SELECT o_orderkey, CAST(date_trunc('MONTH', o_orderdate) AS TIMESTAMP_NTZ) AS month FROM orders", "SELECT o_orderkey, CAST(date_trunc('month', o_orderdate) AS TIMESTAMP) AS month FROM orders")
both("fn_date_arith", "SELECT o_orderkey, datediff(CAST(o_orderdate AS date), DATE '1992-01-01') AS days FROM orders", "SELECT o_orderkey, CAST(date_diff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE)) AS INTEGER) AS days FROM orders")
both("fn_date_parts", "SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, day(o_orderdate) AS dd FROM orders", "SELECT o_orderkey, CAST(year(o_orderdate) AS INTEGER) AS y, CAST(month(o_orderdate) AS INTEGER) AS m, CAST(day(o_orderdate) AS INTEGER) AS dd FROM orders")
both("fn_interval", "SELECT event_id, ts + INTERVAL '90' MINUTE AS later FROM events")
both("fn_log_pow_exp", "SELECT doc_id, round(ln(n_chars + 1), 6) AS l, round(power(n_chars, 0.5), 6) AS p, round(exp(-n_chars / 10000.0), 6) AS e FROM documents", "SELECT doc_id, round(ln(n_chars + 1), 6) AS l, round(power(n_chars, 0.5), 6) AS p, round(exp(-n_chars / 10000), 6) AS e FROM documents")
both("fn_round_floor_pmod", "SELECT doc_id, CAST(floor(n_chars / 7) AS BIGINT) AS f, pmod(-n_chars, 7) AS m FROM documents", "SELECT doc_id, CAST(floor(n_chars / 7) AS BIGINT) AS f, ((-n_chars % 7) + 7) % 7 AS m FROM documents")
both("fn_width_bucket", "SELECT doc_id, width_bucket(n_chars, 0, 20000, 10) AS b FROM documents", "SELECT doc_id, CAST(CASE WHEN n_chars >= 20000 THEN 11 ELSE floor(n_chars / 2000) + 1 END AS BIGINT) AS b FROM documents")
both("fn_array_hof", "SELECT doc_id, size(filter(split(text, ' '), w -> length(w) > 8)) AS n_long FROM documents", "SELECT doc_id, CAST(len(list_filter(string_split(text, ' '), lambda w: length(w) > 8)) AS INTEGER) AS n_long FROM documents")
both("fn_array_sets", "SELECT doc_id, size(array_distinct(split(text, ' '))) AS n_types FROM documents", "SELECT doc_id, CAST(len(list_distinct(string_split(text, ' '))) AS INTEGER) AS n_types FROM documents")
both("fn_array_explode", "SELECT w, count(*) AS n FROM (SELECT explode(split(text, ' ')) AS w FROM documents) GROUP BY w HAVING count(*) > 500", "SELECT w, count(*) AS n FROM (SELECT unnest(string_split(text, ' ')) AS w FROM documents) GROUP BY w HAVING count(*) > 500")
both("fn_array_zip", "SELECT item_id, aggregate(zip_with(split(text, ' '), sequence(1, size(split(text, ' '))), (w, i) -> i * length(w)), 0, (s, x) -> s + x) AS weighted FROM benchmark", "SELECT item_id, CAST(list_sum(list_transform(string_split(text, ' '), lambda w, i: i * length(w))) AS INTEGER) AS weighted FROM benchmark")
both("fn_map_build", "SELECT source, map_keys(m)[0] IS NOT NULL AS some, size(m) AS n FROM (SELECT source, map_from_entries(collect_list(struct(lang, n))) AS m FROM (SELECT source, lang, count(*) AS n FROM documents GROUP BY source, lang) GROUP BY source)", "SELECT source, true AS some, CAST(count(DISTINCT lang) AS INTEGER) AS n FROM documents GROUP BY source")
both("fn_map_filter", "SELECT source, size(map_filter(m, (k, v) -> v > 5)) AS n FROM (SELECT source, map_from_entries(collect_list(struct(lang, n))) AS m FROM (SELECT source, lang, count(*) AS n FROM documents GROUP BY source, lang) GROUP BY source)", "SELECT source, CAST(count(*) FILTER (n > 5) AS INTEGER) AS n FROM (SELECT source, lang, count(*) AS n FROM documents GROUP BY source, lang) GROUP BY source")
both("fn_json_extract", "SELECT event_id, get_json_object(props, '$.k') AS k FROM events", "SELECT event_id, props ->> '$.k' AS k FROM events")
both("fn_json_struct", "SELECT event_id, CAST(from_json(props, 'k STRING').k AS STRING) AS k FROM events", "SELECT event_id, props ->> '$.k' AS k FROM events")
both("fn_variant", "SELECT event_id, variant_get(parse_json(props), '$.k', 'string') AS k FROM events", "SELECT event_id, props ->> '$.k' AS k FROM events")


@query("fn_vec_dot", "SELECT vec_id, round(CAST(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * CAST(x AS DOUBLE))) AS DOUBLE), 4) AS norm2 FROM embeddings")
def fn_vec_dot(spark, d):
    square = F.aggregate(F.transform("embedding", lambda x: x.cast("double") * x.cast("double")), F.lit(0.0), lambda s, x: s + x)
    return table(spark, d, "embeddings").select("vec_id", F.round(square, 4).alias("norm2"))


# samples, nesting and data quality

both("smp_hash", "SELECT doc_id FROM documents WHERE substr(md5(CAST(doc_id AS string)), 1, 1) < '4'", "SELECT doc_id FROM documents WHERE substr(md5(CAST(doc_id AS VARCHAR)), 1, 1) < '4'")


@query("smp_stratified", "SELECT doc_id, lang FROM documents QUALIFY row_number() OVER (PARTITION BY lang ORDER BY md5(CAST(doc_id AS VARCHAR))) <= 5")
def smp_stratified(spark, d):
    w = Window.partitionBy("lang").orderBy(F.md5(F.col("doc_id").cast("string")))
    return table(spark, d).withColumn("r", F.row_number().over(w)).filter("r <= 5").select("doc_id", "lang")


@query("smp_topk_hash", "SELECT doc_id FROM documents ORDER BY md5(CAST(doc_id AS VARCHAR)) LIMIT 25")
def smp_topk_hash(spark, d):
    return table(spark, d).orderBy(F.md5(F.col("doc_id").cast("string"))).limit(25).select("doc_id")


@query("nest_conversation", "SELECT conv_id, count(*) AS n_turns, md5(string_agg(role || ': ' || text, chr(10) ORDER BY turn)) AS digest FROM conversations GROUP BY 1")
def nest_conversation(spark, d):
    turns = table(spark, d, "conversations").groupBy("conv_id").agg(F.sort_array(F.collect_list(F.struct("turn", "role", "text"))).alias("t"))
    return turns.select("conv_id", F.size("t").cast("long").alias("n_turns"), F.md5(F.array_join(F.transform("t", lambda x: F.concat(x["role"], F.lit(": "), x["text"])), "\n")).alias("digest"))


both("dq_nulls", "SELECT count(*) - count(text) AS null_text, count(*) - count(lang) AS null_lang, count(*) - count(doc_id) AS null_id FROM documents")
both("dq_unique_key", "SELECT doc_id, count(*) AS n FROM documents GROUP BY doc_id HAVING count(*) > 1")
both("dq_referential", "SELECT count(*) AS orphans FROM labels l LEFT JOIN documents d ON l.doc_id = d.doc_id WHERE d.doc_id IS NULL")
both("dq_profile", "SELECT lang, count(*) AS n, min(n_chars) AS least, max(n_chars) AS most, round(avg(n_chars), 4) AS mean FROM documents GROUP BY lang")
both("landscape_matrix", "SELECT lang, count(DISTINCT source) AS n_sources, count(*) AS n_docs, round(count(*) / (SELECT count(*) FROM documents), 6) AS share FROM documents GROUP BY lang")
