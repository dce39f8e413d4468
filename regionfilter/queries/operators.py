"""Queries of the relational operators around the methods: scans, joins, aggregations, windows, set operations."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from .. import workloads as W
from ..functions.hashing import bucket, positions, u60_sql
from ..functions.formulas import seg_of
from ..functions.sql import register
from ..sources.io import table
from .methods import dec
from .oracle import dec as sdec

QUERIES: dict = {}
ORACLES: dict = {}


def add(name: str, sql: str | None = None):
    def keep(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return keep


@add("op_scan_pruned", "SELECT l_orderkey, l_quantity FROM lineitem WHERE l_shipdate >= TIMESTAMP '1998-01-01' AND l_quantity > 45")
def scan_pruned(spark, sf_dir):
    return table(spark, sf_dir, "lineitem", "l_orderkey", "l_quantity", "l_shipdate").where("l_shipdate >= TIMESTAMP '1998-01-01' AND l_quantity > 45").select("l_orderkey", "l_quantity")


_COUNTS = {"question": "?", "hash": "#", "slash": "/", "dot": ".", "dash": "-", "equals": "=", "amp": "&"}
_HOST, _PATH = "regexp_extract(url, '://([^/?#]*)', 1)", "regexp_extract(url, '://[^/?#]*([^?#]*)', 1)"


@add("op_features_url", "SELECT page_id, length(url)::INT AS f_length, length(" + _HOST + ")::INT AS f_host, length(" + _PATH + ")::INT AS f_path, (length(url) - length(regexp_replace(url, '[0-9]', '', 'g')))::INT AS f_digits, " + ", ".join(f"(length(url) - length(replace(url, '{c}', '')))::INT AS f_{n}" for n, c in _COUNTS.items()) + f", starts_with(url, 'https')::INT AS f_https, CASE WHEN starts_with({_HOST}, 'www.') THEN 1 WHEN starts_with({_HOST}, 'm.') THEN 2 ELSE 0 END::INT AS f_sub, length(regexp_extract({_HOST}, '\\.([a-z]+)$', 1))::INT AS f_tld, (length({_PATH}) - length(replace({_PATH}, '/', '')))::INT AS f_depth, contains(url, '.html')::INT AS f_html, contains(url, 'utm_source')::INT AS f_utm FROM pages WHERE url IS NOT NULL")
def features_url(spark, sf_dir):
    return W.url_features(table(spark, sf_dir, "pages", "page_id", "url").where("url is not null")).drop("url")


@add("op_features_doc", "SELECT doc_id, length(text)::INT AS n, (length(text) - length(replace(text, '\n', '')))::INT AS lines, (length(text) - length(regexp_replace(text, '[0-9]', '', 'g')))::INT AS digits FROM documents WHERE text IS NOT NULL")
def features_doc(spark, sf_dir):
    t = table(spark, sf_dir, "documents", "doc_id", "text").where("text is not null")
    return t.select("doc_id", F.length("text").alias("n"), (F.length("text") - F.length(F.replace("text", F.lit("\n"), F.lit("")))).alias("lines"), (F.length("text") - F.length(F.regexp_replace("text", "[0-9]", ""))).alias("digits"))


@add("op_filter_pred", "SELECT o_orderkey, o_orderstatus FROM orders WHERE o_totalprice BETWEEN 1000 AND 200000 AND o_orderpriority IN ('1-URGENT', '2-HIGH') AND o_orderstatus LIKE 'F%' AND regexp_matches(o_orderpriority, '^[12]-') AND o_custkey IS NOT NULL")
def filter_pred(spark, sf_dir):
    t = table(spark, sf_dir, "orders", "o_orderkey", "o_orderstatus", "o_totalprice", "o_orderpriority", "o_custkey")
    return t.where(F.col("o_totalprice").between(1000, 200000) & F.col("o_orderpriority").isin("1-URGENT", "2-HIGH") & F.col("o_orderstatus").like("F%") & F.col("o_orderpriority").rlike("^[12]-") & F.col("o_custkey").isNotNull()).select("o_orderkey", "o_orderstatus")


@add("op_join_equi", "SELECT o_orderpriority, count(*) AS n, sum(l_quantity) AS quantity FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_orderpriority")
def join_equi(spark, sf_dir):
    o, l = table(spark, sf_dir, "orders", "o_orderkey", "o_orderpriority"), table(spark, sf_dir, "lineitem", "l_orderkey", "l_quantity")  # noqa: E741
    return l.join(o, l.l_orderkey == o.o_orderkey).groupBy("o_orderpriority").agg(F.count("*").alias("n"), F.sum("l_quantity").alias("quantity"))


@add("op_join_shuffled_hash", ORACLES["op_join_equi"])
def join_shuffled_hash(spark, sf_dir):
    o, l = table(spark, sf_dir, "orders", "o_orderkey", "o_orderpriority"), table(spark, sf_dir, "lineitem", "l_orderkey", "l_quantity")  # noqa: E741
    return l.join(o.hint("shuffle_hash"), l.l_orderkey == o.o_orderkey).groupBy("o_orderpriority").agg(F.count("*").alias("n"), F.sum("l_quantity").alias("quantity"))


@add("op_join_merge", ORACLES["op_join_equi"])
def join_merge(spark, sf_dir):
    o, l = table(spark, sf_dir, "orders", "o_orderkey", "o_orderpriority"), table(spark, sf_dir, "lineitem", "l_orderkey", "l_quantity")  # noqa: E741
    return l.join(o.hint("merge"), l.l_orderkey == o.o_orderkey).groupBy("o_orderpriority").agg(F.count("*").alias("n"), F.sum("l_quantity").alias("quantity"))


@add("op_join_broadcast", "SELECT n_name, r_name FROM nation JOIN region ON n_regionkey = r_regionkey")
def join_broadcast(spark, sf_dir):
    return table(spark, sf_dir, "nation").join(F.broadcast(table(spark, sf_dir, "region")), F.col("n_regionkey") == F.col("r_regionkey")).select("n_name", "r_name")  # five rows at any scale


@add("op_join_outer", "SELECT coalesce(c_nationkey, s_nationkey) AS nation, coalesce(c, 0) AS customers, coalesce(s, 0) AS suppliers FROM (SELECT c_nationkey, count(*) AS c FROM customer WHERE c_acctbal > 9000 GROUP BY 1) FULL JOIN (SELECT s_nationkey, count(*) AS s FROM supplier WHERE s_acctbal > 5000 GROUP BY 1) ON c_nationkey = s_nationkey")
def join_outer(spark, sf_dir):
    c = table(spark, sf_dir, "customer").where("c_acctbal > 9000").groupBy(F.col("c_nationkey").alias("nation")).agg(F.count("*").alias("customers"))
    s = table(spark, sf_dir, "supplier").where("s_acctbal > 5000").groupBy(F.col("s_nationkey").alias("nation")).agg(F.count("*").alias("suppliers"))
    return c.join(s, "nation", "full").fillna(0, ["customers", "suppliers"])


@add("op_semi_exact", "SELECT count(*) AS n FROM lineitem WHERE l_orderkey IN (SELECT o_orderkey FROM orders WHERE o_orderpriority = '1-URGENT')")
def semi_exact(spark, sf_dir):
    o = table(spark, sf_dir, "orders", "o_orderkey", "o_orderpriority").where("o_orderpriority = '1-URGENT'")
    return table(spark, sf_dir, "lineitem", "l_orderkey").join(o, F.col("l_orderkey") == F.col("o_orderkey"), "left_semi").agg(F.count("*").alias("n"))


@add("op_anti_nonkeys", "SELECT count(*) AS n FROM lineitem WHERE l_orderkey NOT IN (SELECT o_orderkey FROM orders WHERE o_orderpriority = '1-URGENT')")
def anti_nonkeys(spark, sf_dir):
    o = table(spark, sf_dir, "orders", "o_orderkey", "o_orderpriority").where("o_orderpriority = '1-URGENT'")
    return table(spark, sf_dir, "lineitem", "l_orderkey").join(o, F.col("l_orderkey") == F.col("o_orderkey"), "left_anti").agg(F.count("*").alias("n"))


@add("op_asof_plan", "SELECT event_id, max(v.day) AS plan_day FROM events JOIN (SELECT DISTINCT date_trunc('day', ts)::TIMESTAMP AS day FROM events WHERE event_type = 'purchase') v ON v.day <= ts GROUP BY event_id")
def asof_plan(spark, sf_dir):
    """The daily plan version in force at each event, versions being the days with a purchase: union of both sides, and the last version seen in time order
    within a month (the version table's grain), carried over months by one more look-up of month ends."""
    e = table(spark, sf_dir, "events", "event_id", "ts", "event_type")
    v = e.where("event_type = 'purchase'").select(F.date_trunc("day", "ts").alias("day")).distinct()
    both = e.select("event_id", "ts", F.lit(None).cast("timestamp").alias("day")).unionByName(v.select(F.lit(None).cast("bigint").alias("event_id"), F.col("day").alias("ts"), "day"))
    both = both.withColumn("month", F.date_trunc("month", "ts"))
    run = Window.partitionBy("month").orderBy("ts", F.col("day").isNull().cast("int")).rowsBetween(Window.unboundedPreceding, 0)
    inside = both.withColumn("found", F.last("day", ignorenulls=True).over(run)).where("event_id is not null")
    ends = v.groupBy(F.date_trunc("month", "day").alias("m")).agg(F.max("day").alias("last_day"))  # a row a month
    months = inside.select("month").distinct().join(ends, F.col("m") < F.col("month")).groupBy("month").agg(F.max("last_day").alias("carried"))
    return inside.join(F.broadcast(months), "month", "left").select("event_id", F.coalesce("found", "carried").alias("plan_day")).where("plan_day is not null")


@add("op_interval_join", "SELECT a.event_id AS probe, b.event_id AS key FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts < a.ts AND b.ts >= a.ts - INTERVAL 1 HOUR")
def interval_join(spark, sf_dir):
    e = table(spark, sf_dir, "events", "event_id", "user_id", "ts")
    hour = lambda ts: F.floor(F.unix_timestamp(ts.cast("timestamp")) / 3600)
    # a key is listed for its hour and the next one, so that a user's keys of other times are never met
    a = e.select(F.col("event_id").alias("probe"), "user_id", F.col("ts").alias("ta"), hour(F.col("ts")).alias("at"))
    b = e.select(F.col("event_id").alias("key"), "user_id", F.col("ts").alias("tb"), F.explode(F.array(hour(F.col("ts")), hour(F.col("ts")) + 1)).alias("at"))
    return a.join(b, ["user_id", "at"]).where("tb < ta AND tb >= ta - INTERVAL 1 HOUR").select("probe", "key")


@add("op_agg_basic", f"SELECT l_returnflag, l_linestatus, count(*) AS n, sum(l_quantity) AS quantity, {sdec('avg(l_discount)')} AS discount, min(l_tax) AS low, max(l_tax) AS high FROM lineitem GROUP BY ALL")
def agg_basic(spark, sf_dir):
    t = table(spark, sf_dir, "lineitem", "l_returnflag", "l_linestatus", "l_quantity", "l_discount", "l_tax")
    return t.groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.sum("l_quantity").alias("quantity"), dec(F.avg("l_discount")).alias("discount"), F.min("l_tax").alias("low"), F.max("l_tax").alias("high"))


@add("op_bitmap_distinct", "SELECT o_orderstatus, count(DISTINCT o_custkey) AS customers FROM orders GROUP BY o_orderstatus")
def bitmap_distinct(spark, sf_dir):
    """Distinct counts by built-in bitmaps of 32768 bits."""
    t = table(spark, sf_dir, "orders", "o_orderstatus", "o_custkey")
    maps = t.groupBy("o_orderstatus", F.bitmap_bucket_number("o_custkey").alias("b")).agg(F.bitmap_count(F.bitmap_construct_agg(F.bitmap_bit_position("o_custkey"))).alias("n"))
    return maps.groupBy("o_orderstatus").agg(F.sum("n").alias("customers"))


@add("op_distinct_keys", "SELECT count(DISTINCT l_partkey) AS parts FROM lineitem")
def distinct_keys(spark, sf_dir):
    return table(spark, sf_dir, "lineitem", "l_partkey").agg(F.count_distinct("l_partkey").alias("parts"))


@add("op_cube_fp", "SELECT l_returnflag, l_linestatus, grouping_id(l_returnflag, l_linestatus)::BIGINT AS g, count(*) FILTER (WHERE l_discount > 0.05) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
def cube_fp(spark, sf_dir):
    return table(spark, sf_dir, "lineitem", "l_returnflag", "l_linestatus", "l_discount").cube("l_returnflag", "l_linestatus").agg(F.grouping_id().alias("g"), F.count_if(F.col("l_discount") > 0.05).alias("n"))


@add("op_rollup_docs", "SELECT lang, source, count(*) AS n, sum(n_chars)::BIGINT AS chars FROM documents GROUP BY ROLLUP (lang, source)")
def rollup_docs(spark, sf_dir):
    return table(spark, sf_dir, "documents", "lang", "source", "n_chars").rollup("lang", "source").agg(F.count("*").alias("n"), F.sum("n_chars").alias("chars"))


@add("op_grouping_sets", "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority))")
def grouping_sets(spark, sf_dir):
    t = table(spark, sf_dir, "orders", "o_orderstatus", "o_orderpriority")
    return t.groupingSets([["o_orderstatus"], ["o_orderpriority"]], "o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"))


@add("op_max_by", "SELECT user_id, arg_max(event_id, (ts, event_id)) AS last_event FROM events GROUP BY user_id")
def max_by(spark, sf_dir):
    return table(spark, sf_dir, "events", "user_id", "event_id", "ts").groupBy("user_id").agg(F.max_by("event_id", F.struct("ts", "event_id")).alias("last_event"))


@add("op_pivot_sizes", "SELECT l_returnflag, count(*) FILTER (WHERE l_linestatus = 'F') AS F, count(*) FILTER (WHERE l_linestatus = 'O') AS O FROM lineitem GROUP BY l_returnflag")
def pivot_sizes(spark, sf_dir):
    return table(spark, sf_dir, "lineitem", "l_returnflag", "l_linestatus").groupBy("l_returnflag").pivot("l_linestatus", ["F", "O"]).agg(F.count(F.lit(1))).fillna(0)


@add("op_rank", f"SELECT doc_id, row_number() OVER w AS rn, rank() OVER v AS rk, dense_rank() OVER v AS dr, ntile(4) OVER w AS nt, {sdec('percent_rank() OVER v')} AS pr FROM documents WINDOW w AS (PARTITION BY lang, source ORDER BY n_chars, doc_id), v AS (PARTITION BY lang, source ORDER BY n_chars)")
def rank(spark, sf_dir):
    by = Window.partitionBy("lang", "source")
    w, v = by.orderBy("n_chars", "doc_id"), by.orderBy("n_chars")
    return table(spark, sf_dir, "documents", "doc_id", "lang", "source", "n_chars").select("doc_id", F.row_number().over(w).cast("bigint").alias("rn"), F.rank().over(v).cast("bigint").alias("rk"), F.dense_rank().over(v).cast("bigint").alias("dr"), F.ntile(4).over(w).cast("bigint").alias("nt"), dec(F.percent_rank().over(v)).alias("pr"))


@add("op_lag_lead", "SELECT event_id, lag(event_id) OVER w AS before, lead(event_id) OVER w AS after, first_value(event_id) OVER w AS first FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def lag_lead(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return table(spark, sf_dir, "events", "event_id", "user_id", "ts").select("event_id", F.lag("event_id").over(w).alias("before"), F.lead("event_id").over(w).alias("after"), F.first("event_id").over(w).alias("first"))


@add("op_range_frame", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch(ts)::BIGINT RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW) AS n FROM events")
def range_frame(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy(F.round(F.unix_micros(F.col("ts").cast("timestamp")) / 1e6).cast("bigint")).rangeBetween(-86400, 0)
    return table(spark, sf_dir, "events", "event_id", "user_id", "ts").select("event_id", F.count("*").over(w).alias("n"))


@add("op_topk", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20 OFFSET 5")
def topk(spark, sf_dir):
    return table(spark, sf_dir, "orders", "o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").offset(5).limit(20)


@add("op_setops", "SELECT 'both' AS part, count(*) AS n FROM (SELECT l_partkey FROM lineitem WHERE l_quantity > 40 INTERSECT SELECT l_partkey FROM lineitem WHERE l_quantity < 10) UNION ALL SELECT 'only', count(*) FROM (SELECT l_partkey FROM lineitem WHERE l_quantity > 40 EXCEPT SELECT l_partkey FROM lineitem WHERE l_quantity < 10)")
def setops(spark, sf_dir):
    t = table(spark, sf_dir, "lineitem", "l_partkey", "l_quantity")
    a, b = t.where("l_quantity > 40").select("l_partkey"), t.where("l_quantity < 10").select("l_partkey")
    return a.intersect(b).agg(F.lit("both").alias("part"), F.count("*").alias("n")).unionByName(a.exceptAll(b).join(b, "l_partkey", "left_anti").distinct().agg(F.lit("only").alias("part"), F.count("*").alias("n")))


@add("op_dedupe_docs", "SELECT md5(text) AS elem, max((quality = 0)::INT) AS is_key FROM documents JOIN labels USING (doc_id) WHERE text IS NOT NULL GROUP BY 1")
def dedupe_docs(spark, sf_dir):
    from ..operators.elements import universe

    return universe(W.docs(spark, sf_dir)).select("elem", "is_key")


@add("op_sample_bucket", f"SELECT o_orderstatus, count(*) AS n FROM orders WHERE {u60_sql("o_orderkey::VARCHAR || '#sample'")} % 100 < 10 GROUP BY o_orderstatus")
def sample_bucket(spark, sf_dir):
    """A repeatable tenth of the orders: the sampling operator itself."""
    return table(spark, sf_dir, "orders", "o_orderkey", "o_orderstatus").where(bucket(F.col("o_orderkey").cast("string"), "sample") < 10).groupBy("o_orderstatus").agg(F.count("*").alias("n"))


@add("op_hash_positions", f"SELECT o_orderkey, array_to_string(list_transform(range(5), lambda i: ({u60_sql('o_orderkey::VARCHAR')} % 1009 + i * (({u60_sql("o_orderkey::VARCHAR || '#2'")} | 1) % 1009)) % 1009), ',') AS positions FROM orders")
def hash_positions(spark, sf_dir):
    return table(spark, sf_dir, "orders", "o_orderkey").select("o_orderkey", F.array_join(positions(F.col("o_orderkey").cast("string"), 5, 1009).cast("array<string>"), ",").alias("positions"))


@add("op_month_cells", "SELECT date_trunc('month', o_orderdate)::TIMESTAMP AS month, count(*) AS n, avg(o_orderpriority = '1-URGENT')::DOUBLE >= 0.2 AS dense FROM orders GROUP BY 1".replace("avg(o_orderpriority = '1-URGENT')::DOUBLE >= 0.2", "5 * count(*) FILTER (WHERE o_orderpriority = '1-URGENT') >= count(*)"))
def month_cells(spark, sf_dir):
    return table(spark, sf_dir, "orders", "o_orderdate", "o_orderpriority").groupBy(F.date_trunc("month", "o_orderdate").alias("month")).agg(F.count("*").alias("n"), (5 * F.count_if(F.col("o_orderpriority") == "1-URGENT") >= F.count("*")).alias("dense"))


@add("op_vec_dot", f"SELECT vec_id, {sdec('list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE))')} AS dot FROM embeddings WHERE embedding IS NOT NULL")
def vec_dot(spark, sf_dir):
    return table(spark, sf_dir, "embeddings", "vec_id", "embedding").where("embedding is not null").select("vec_id", dec(F.aggregate("embedding", F.lit(0.0), lambda s, x: s + x.cast("double") * x.cast("double"))).alias("dot"))


@add("op_map_struct", "SELECT o_orderstatus, max(n) AS most FROM (SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY ALL) GROUP BY o_orderstatus")
def map_struct(spark, sf_dir):
    n = table(spark, sf_dir, "orders", "o_orderstatus", "o_orderpriority").groupBy("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"))
    m = n.groupBy("o_orderstatus").agg(F.map_from_entries(F.collect_list(F.struct("o_orderpriority", "n"))).alias("m"))  # five priorities
    return m.select("o_orderstatus", F.array_max(F.map_values("m")).alias("most"))


@add("op_json_props", "SELECT event_type, sum(CAST(json_extract_string(props, '$.k') AS BIGINT))::BIGINT AS k FROM events GROUP BY event_type")
def json_props(spark, sf_dir):
    return table(spark, sf_dir, "events", "event_type", "props").groupBy("event_type").agg(F.sum(F.from_json("props", "k bigint")["k"]).alias("k"))


@add("op_shingles", "SELECT item_id, len(list_distinct(list_transform(range(1, len(w) - 1), lambda i: array_to_string(w[i:i + 2], ' '))))::INT AS n FROM (SELECT item_id, list_filter(regexp_split_to_array(lower(coalesce(text, '')), '\\s+'), lambda w: w <> '') AS w FROM benchmark) WHERE len(w) >= 3")
def shingles_(spark, sf_dir):
    from ..functions.formulas import shingles

    return table(spark, sf_dir, "benchmark", "item_id", "text").select("item_id", F.size(F.array_distinct(shingles(F.col("text"), 3))).alias("n")).where("n > 0")


_ODD_SCORE = "CASE c_custkey % 7 WHEN 0 THEN NULL WHEN 1 THEN {nan} ELSE c_acctbal / 9000 END"


@add("op_null_scores", f"SELECT c_custkey AS i, CASE WHEN score IS NULL OR isnan(score) THEN 0 ELSE least(19, greatest(0, floor(least(greatest(round(score, 9), 0), 1) * 20)))::INT END AS seg FROM (SELECT c_custkey, {_ODD_SCORE.format(nan="'NaN'::DOUBLE")} AS score FROM customer)")
def null_scores(spark, sf_dir):
    """Segments of scores that may be null, NaN, below 0 and above 1: balances of customers."""
    d = table(spark, sf_dir, "customer", "c_custkey", "c_acctbal").withColumn("score", F.expr(_ODD_SCORE.format(nan="double('NaN')")))
    return d.select(F.col("c_custkey").alias("i"), seg_of(F.col("score"), 20).alias("seg"))


@add("op_sql_udf", f"SELECT l_returnflag, {sdec('sum(a * log2(a / b))')} AS divergence FROM (SELECT l_returnflag, count(*) FILTER (WHERE l_discount > 0.05)::DOUBLE / sum(count(*) FILTER (WHERE l_discount > 0.05)) OVER () AS a, count(*)::DOUBLE / sum(count(*)) OVER () AS b FROM lineitem GROUP BY l_returnflag) GROUP BY l_returnflag")
def sql_udf(spark, sf_dir):
    register(spark)
    table(spark, sf_dir, "lineitem", "l_returnflag", "l_discount").createOrReplaceTempView("rf_lineitem")
    return spark.sql("SELECT l_returnflag, CAST(CAST(kl_term(a, b) AS DECIMAL(18, 6)) AS DOUBLE) AS divergence FROM (SELECT l_returnflag, count_if(l_discount > 0.05) / sum(count_if(l_discount > 0.05)) OVER () AS a, count(*) / sum(count(*)) OVER () AS b FROM rf_lineitem GROUP BY l_returnflag)")


@add("op_exists_keys", "SELECT count(*) AS n FROM orders o WHERE EXISTS (SELECT 1 FROM lineitem l WHERE l.l_orderkey = o.o_orderkey AND l.l_quantity > 49) AND o_totalprice > (SELECT avg(o_totalprice) FROM orders)")
def exists_keys(spark, sf_dir):
    table(spark, sf_dir, "lineitem").createOrReplaceTempView("rf_lineitem")
    table(spark, sf_dir, "orders").createOrReplaceTempView("rf_orders")
    return spark.sql("SELECT count(*) AS n FROM rf_orders o WHERE EXISTS (SELECT 1 FROM rf_lineitem l WHERE l.l_orderkey = o.o_orderkey AND l.l_quantity > 49) AND o_totalprice > (SELECT avg(o_totalprice) FROM rf_orders)")


@add("op_recursive_cte", "WITH RECURSIVE c(l_returnflag, i, n) AS (SELECT l_returnflag, 1, sum(l_quantity)::BIGINT FROM lineitem GROUP BY l_returnflag UNION ALL SELECT l_returnflag, i + 1, n * 2 FROM c WHERE i < 20) SELECT l_returnflag, i, n FROM c")
def recursive_cte(spark, sf_dir):
    """Twenty doublings of the quantity sold under each flag."""
    table(spark, sf_dir, "lineitem", "l_returnflag", "l_quantity").groupBy("l_returnflag").agg(F.sum("l_quantity").cast("bigint").alias("n")).createOrReplaceTempView("rf_quantities")
    return spark.sql("WITH RECURSIVE c(l_returnflag, i, n) AS (SELECT l_returnflag, 1, n FROM rf_quantities UNION ALL SELECT l_returnflag, i + 1, n * 2 FROM c WHERE i < 20) SELECT l_returnflag, i, n FROM c")


@add("op_udtf_best_cuts")
def udtf_best_cuts(spark, sf_dir):
    """Cuts by a table function in SQL."""
    from .methods import scored

    register(spark)
    scored(spark, sf_dir, "line").hist().createOrReplaceTempView("rf_hist")
    return spark.sql("SELECT * FROM best_cuts(TABLE(SELECT seg, kc, qc FROM rf_hist) WITH SINGLE PARTITION, 4)")


@add("stream_probe_rows")
def stream_probe_rows(spark, sf_dir):
    """Events as a stream, probed against a filter and counted by hour; the stream ends when its files are read."""
    from ..streaming.probe import run_probe_counts

    return run_probe_counts(spark, sf_dir)
