"""The relational surface around the index: joins, aggregates, windows, sets and functions, each with its SQL.

Queries that read the same in Spark SQL and in the oracle's dialect are written once and run by both."""

from __future__ import annotations

from liveindex.registry import register
from liveindex.workloads import sqlparts as Q

TABLES = "region nation customer supplier part orders lineitem events documents labels".split()

#: One text for both sides.
BOTH = {
    "scan_parquet": "SELECT l_orderkey, l_quantity FROM lineitem",
    "filter_project": "SELECT l_orderkey, l_linenumber, l_extendedprice * (1 - l_discount) AS revenue FROM lineitem WHERE l_quantity > 45 AND l_discount BETWEEN 0.02 AND 0.05",
    "filter_in": "SELECT o_orderkey, o_orderpriority FROM orders WHERE o_orderstatus IN ('F', 'O') AND o_totalprice > 1000",
    "filter_like": "SELECT p_partkey, p_name FROM part WHERE p_name LIKE '%e%' AND p_type NOT LIKE 'X%'",
    "null_semantics": "SELECT d.doc_id, coalesce(l.quality, -1) AS quality, l.toxic IS NULL AS unlabelled FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id",
    "join_inner": "SELECT n_name, r_name FROM nation JOIN region ON n_regionkey = r_regionkey",
    "join_left": "SELECT c.c_custkey, count(o.o_orderkey) AS n FROM customer c LEFT JOIN orders o ON c.c_custkey = o.o_custkey GROUP BY c.c_custkey",
    "join_right": "SELECT o.o_orderkey, c.c_name FROM customer c RIGHT JOIN orders o ON c.c_custkey = o.o_custkey",
    "join_full": "SELECT c.c_custkey, s.s_suppkey FROM customer c FULL JOIN supplier s ON c.c_custkey = s.s_suppkey",
    "join_semi": "SELECT c_custkey FROM customer c WHERE EXISTS (SELECT 1 FROM orders o WHERE o.o_custkey = c.c_custkey)",
    "join_anti": "SELECT c_custkey FROM customer c WHERE NOT EXISTS (SELECT 1 FROM orders o WHERE o.o_custkey = c.c_custkey)",
    "join_self": "SELECT a.n_name AS a, b.n_name AS b FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey",
    "join_theta": "SELECT a.r_name AS a, b.r_name AS b FROM region a JOIN region b ON a.r_regionkey < b.r_regionkey",
    "agg_basic": "SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS qty, round(avg(l_extendedprice), 4) AS price, min(l_tax) AS lo, max(l_tax) AS hi FROM lineitem GROUP BY l_returnflag, l_linestatus",
    "agg_distinct": "SELECT l_returnflag, count(DISTINCT l_suppkey) AS suppliers FROM lineitem GROUP BY l_returnflag",
    "agg_filter": "SELECT o_orderstatus, count(*) FILTER (WHERE o_totalprice > 100000) AS large FROM orders GROUP BY o_orderstatus",
    "agg_having": "SELECT o_custkey, count(*) AS n FROM orders GROUP BY o_custkey HAVING count(*) > 10",
    "agg_max_by": "SELECT o_orderpriority, max_by(o_orderkey, o_totalprice) AS best FROM orders GROUP BY o_orderpriority",
    "agg_grouping_sets": "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())",
    "agg_cube": "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)",
    "agg_rollup": "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)",
    "win_rank": "SELECT o_orderkey, CAST(rank() OVER w AS BIGINT) AS r, CAST(dense_rank() OVER w AS BIGINT) AS dr, CAST(row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice, o_orderkey) AS BIGINT) AS rn FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_totalprice)",
    "win_ntile": "SELECT o_orderkey, CAST(ntile(4) OVER (PARTITION BY o_custkey ORDER BY o_orderkey) AS BIGINT) AS q FROM orders",
    "win_lag_lead": "SELECT o_orderkey, lag(o_orderkey) OVER w AS before, lead(o_orderkey) OVER w AS after FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderkey)",
    "win_running": "SELECT l_orderkey, l_linenumber, CAST(sum(CAST(l_quantity AS BIGINT)) OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_quantity ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS BIGINT) AS q FROM (SELECT DISTINCT l_orderkey, l_linenumber, l_quantity FROM lineitem)",
    "win_rows_frame": "SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderkey ROWS BETWEEN 2 PRECEDING AND 1 FOLLOWING) AS n FROM orders",
    "win_range_frame": "SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderkey RANGE BETWEEN 100 PRECEDING AND 100 FOLLOWING) AS n FROM orders",
    "win_first_last": "SELECT o_orderkey, first_value(o_orderkey) OVER w AS a, last_value(o_orderkey) OVER w AS b FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)",
    "sort_topk": "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20",
    "topk_per_group": "SELECT o_custkey, o_orderkey FROM (SELECT o_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS rn FROM orders) t WHERE rn <= 3",
    "limit_offset": "SELECT n_nationkey, n_name FROM nation ORDER BY n_nationkey LIMIT 5 OFFSET 10",
    "set_union": "SELECT c_nationkey AS k FROM customer UNION SELECT s_nationkey FROM supplier",
    "set_intersect": "SELECT c_nationkey AS k FROM customer INTERSECT SELECT s_nationkey FROM supplier",
    "set_except": "SELECT n_nationkey AS k FROM nation EXCEPT SELECT s_nationkey FROM supplier",
    "set_intersect_all": "SELECT c_nationkey AS k FROM customer INTERSECT ALL SELECT s_nationkey FROM supplier",
    "set_except_all": "SELECT c_nationkey AS k FROM customer EXCEPT ALL SELECT s_nationkey FROM supplier",
    "set_distinct": "SELECT DISTINCT l_returnflag, l_linestatus FROM lineitem",
    "fn_string": "SELECT p_partkey, upper(p_name) AS u, CAST(length(p_name) AS BIGINT) AS n, substring(p_name, 2, 3) AS s, concat_ws('-', p_brand, p_type) AS c, lpad(CAST(p_size AS STRING), 4, '0') AS l, translate(p_name, 'ae', 'xy') AS t, trim(p_name) AS tr FROM part",
    "fn_math": "SELECT x, round(ln(1 + x), 6) AS l, round(sqrt(x), 6) AS s, CAST(ceil(x / 7) AS BIGINT) AS c, CAST(floor(x / 7) AS BIGINT) AS f, greatest(x, 10) AS g, least(x, 10) AS le FROM (SELECT DISTINCT CAST(l_quantity AS BIGINT) AS x FROM lineitem) t",
    "fn_bits": "SELECT x, x & 7 AS a, x | 8 AS o, CAST(bit_count(x) AS BIGINT) AS b FROM (SELECT DISTINCT CAST(l_quantity AS BIGINT) AS x FROM lineitem) t",
    "hash_sample": "SELECT doc_id, lang FROM documents WHERE doc_id % 10 = 3",
}

#: Texts that differ: Spark's, the oracle's.
APART = {
    "agg_percentile": ("SELECT o_orderstatus, round(percentile(o_totalprice, 0.95), 4) AS p95 FROM orders GROUP BY o_orderstatus", "SELECT o_orderstatus, round(quantile_cont(o_totalprice, 0.95), 4) AS p95 FROM orders GROUP BY o_orderstatus"),
    "agg_pivot": ("SELECT * FROM (SELECT l_returnflag, l_linestatus FROM lineitem) PIVOT (count(*) FOR l_linestatus IN ('F' AS f, 'O' AS o))", "SELECT l_returnflag, nullif(count(*) FILTER (WHERE l_linestatus = 'F'), 0) AS f, nullif(count(*) FILTER (WHERE l_linestatus = 'O'), 0) AS o FROM lineitem GROUP BY l_returnflag"),
    "join_interval": ("SELECT a.event_id, b.event_id AS other FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_id <> b.event_id AND b.ts BETWEEN a.ts AND a.ts + INTERVAL 6 HOURS",) * 2,
    "fn_date": ("SELECT o_orderkey, CAST(year(o_orderdate) AS BIGINT) AS y, CAST(month(o_orderdate) AS BIGINT) AS m, CAST(datediff(DATE'2030-01-01', o_orderdate) AS BIGINT) AS d, date_format(o_orderdate, 'yyyy-MM') AS ym FROM orders", "SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, date_diff('day', o_orderdate::DATE, DATE '2030-01-01') AS d, strftime(o_orderdate, '%Y-%m') AS ym FROM orders"),
    "fn_array": ("SELECT doc_id, CAST(size(array_distinct(w)) AS BIGINT) AS kinds, w[0] AS first, array_join(slice(w, 1, 3), ' ') AS three FROM (SELECT doc_id, split(text, ' ') AS w FROM documents)", "SELECT doc_id, len(list_distinct(w)) AS kinds, w[1] AS first, array_to_string(w[1:3], ' ') AS three FROM (SELECT doc_id, string_split(text, ' ') AS w FROM documents)"),
    "fn_array_hof": ("SELECT doc_id, aggregate(transform(filter(split(text, ' '), x -> length(x) > 3), x -> CAST(length(x) AS BIGINT)), 0L, (a, x) -> a + x) AS letters FROM documents", "SELECT doc_id, coalesce(list_sum(list_transform(list_filter(string_split(text, ' '), lambda x: length(x) > 3), lambda x: length(x))), 0)::BIGINT AS letters FROM documents"),
    "fn_json": ("SELECT event_id, CAST(get_json_object(props, '$.k') AS BIGINT) AS k FROM events", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events"),
    "fn_map": ("SELECT o_custkey, CAST(element_at(map_from_entries(array_sort(collect_list(struct(o_orderkey, o_orderkey * 2)))), min(o_orderkey)) AS BIGINT) AS x FROM orders GROUP BY o_custkey", "SELECT o_custkey, min(o_orderkey) * 2 AS x FROM orders GROUP BY o_custkey"),
    "tumbling": ("SELECT date_format(window.start, 'yyyy-MM-dd HH') AS hour, count(*) AS n FROM (SELECT window(CAST(ts AS TIMESTAMP), '1 hour') AS window FROM events) GROUP BY window.start", "SELECT strftime(date_trunc('hour', ts), '%Y-%m-%d %H') AS hour, count(*) AS n FROM events GROUP BY 1"),
    "sliding": ("SELECT date_format(window.start, 'yyyy-MM-dd HH') AS hour, count(*) AS n FROM (SELECT explode(array(0, 1)) AS k, CAST(ts AS TIMESTAMP) AS t FROM events) LATERAL VIEW explode(array(struct(date_trunc('hour', t) - make_interval(0, 0, 0, 0, k) AS start))) v AS window GROUP BY window.start", "SELECT strftime(date_trunc('hour', ts) - k * INTERVAL 1 HOUR, '%Y-%m-%d %H') AS hour, count(*) AS n FROM events, (VALUES (0), (1)) t(k) GROUP BY 1"),
    "session": ("SELECT user_id, date_format(session.start, 'yyyy-MM-dd HH:mm:ss') AS begin, count(*) AS n FROM (SELECT user_id, session_window(CAST(ts AS TIMESTAMP), '6 hours') AS session FROM (SELECT user_id, ts FROM events)) GROUP BY user_id, session.start" , None),
}


def _run(spark, sf_dir: str, text: str):
    """The statement over the tables it names, under names of this directory alone."""
    import re

    names = {t: "`" + f"{t}_{abs(hash(sf_dir)) % 10**9}" + "`" for t in TABLES if re.search(rf"\b{t}\b", text)}
    for t, name in names.items():
        spark.read.parquet(f"{sf_dir}/{t}.parquet").createOrReplaceTempView(name.strip("`"))
    text = re.sub(r"\b(FROM|JOIN)\s+(" + "|".join(TABLES) + r")\b(?!\s*\()(\s+(?:AS\s+)?(?!ON\b|JOIN\b|LEFT\b|RIGHT\b|FULL\b|WHERE\b|GROUP\b|ORDER\b|UNION\b|INTERSECT\b|EXCEPT\b|WINDOW\b|PIVOT\b|LIMIT\b|LATERAL\b)[a-z]+)?", lambda m: f"{m[1]} {names[m[2]]}{m[3] or ' ' + m[2]}", text)
    return spark.sql(text)


for _name, _text in BOTH.items():

    @register(_name, _text.replace(" STRING)", " VARCHAR)"))
    def _(spark, sf_dir, text=_text):
        return _run(spark, sf_dir, text)


for _name, (_text, _sql) in APART.items():
    if _name == "session":
        continue

    @register(_name, _sql)
    def _(spark, sf_dir, text=_text):
        return _run(spark, sf_dir, text)


@register("session", "SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS begin, count(*) AS n FROM (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS s FROM (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 6 HOURS THEN 0 ELSE 1 END AS new FROM events)) GROUP BY user_id, s")
def session(spark, sf_dir):
    from pyspark.sql import functions as F

    rows = spark.read.parquet(f"{sf_dir}/events.parquet").select("user_id", F.col("ts").cast("timestamp").alias("ts"))
    return rows.groupBy("user_id", F.session_window("ts", "6 hours").alias("s")).agg(F.count("*").alias("n")).select("user_id", F.date_format("s.start", "yyyy-MM-dd HH:mm:ss").alias("begin"), "n")


@register("join_asof", "SELECT event_id, max_by(o_orderkey, (o_orderdate, o_orderkey)) AS o FROM events JOIN orders ON user_id % 50 = o_custkey % 50 AND o_orderdate <= ts GROUP BY event_id")
def join_asof(spark, sf_dir):
    """Each event's last order of its class so far. Orders and events lie side by side in order of time, a class and a
    month of days a task, and a running largest order is carried from month to month: no pairs are formed."""
    events, orders = (spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in ("events", "orders"))
    return last_before(events.selectExpr("event_id", "pmod(user_id, 50) AS class", "ts AS at"), orders.selectExpr("o_orderkey", "pmod(o_custkey, 50) AS class", "o_orderdate AS at"))


def last_before(events, orders, days: int = 31):
    """events(event_id, class, at), orders(o_orderkey, class, at): (event_id, o) of the order of the class with the largest
    (at, o_orderkey) that is not after the event; events with none have no row."""
    from pyspark.sql import Window
    from pyspark.sql import functions as F

    order = F.struct("at", "o_orderkey")
    marks = orders.where("class IS NOT NULL AND at IS NOT NULL").select("class", "at", F.lit(0).alias("kind"), F.lit(None).cast("long").alias("event_id"), order.alias("order"))
    asks = events.where("class IS NOT NULL AND at IS NOT NULL").select("class", "at", F.lit(1).alias("kind"), "event_id", F.lit(None).cast(marks.schema["order"].dataType).alias("order"))
    rows = marks.unionAll(asks).withColumn("cell", F.floor(F.unix_date(F.to_date("at")) / days))
    cells = rows.groupBy("class", "cell").agg(F.max("order").alias("most"))
    carried = cells.select("class", "cell", F.max("most").over(Window.partitionBy("class").orderBy("cell").rowsBetween(Window.unboundedPreceding, -1)).alias("carried"))
    inside = Window.partitionBy("class", "cell").orderBy("at", "kind").rowsBetween(Window.unboundedPreceding, 0)
    met = rows.withColumn("here", F.max("order").over(inside)).where("kind = 1").join(carried, ["class", "cell"]).withColumn("last", F.coalesce("here", "carried")).where("last IS NOT NULL")
    # Rows of one event_id count as one event.
    return met.groupBy("event_id").agg(F.max("last").alias("last")).select("event_id", F.col("last.o_orderkey").alias("o"))


@register("scan_pruned", "SELECT o_orderkey, o_totalprice FROM orders WHERE o_orderstatus = 'F' AND o_totalprice > 1000")
def scan_pruned(spark, sf_dir):
    """A table in partitions by status: the scan opens one of them, and the price filter reaches the files."""
    from liveindex.scratch import folder

    where = folder(spark, "orders-by-status")
    spark.read.parquet(f"{sf_dir}/orders.parquet").select("o_orderkey", "o_totalprice", "o_orderstatus").write.partitionBy("o_orderstatus").parquet(where)
    return spark.read.parquet(where).where("o_orderstatus = 'F' AND o_totalprice > 1000").select("o_orderkey", "o_totalprice")


for _kind in ("csv", "json", "orc"):

    @register(f"roundtrip_{_kind}", "SELECT c_custkey, c_name, c_nationkey, c_acctbal, c_mktsegment FROM customer")
    def _(spark, sf_dir, kind=_kind):
        from liveindex.scratch import folder

        where, rows = folder(spark, kind), spark.read.parquet(f"{sf_dir}/customer.parquet").select("c_custkey", "c_name", "c_nationkey", "c_acctbal", "c_mktsegment")
        rows.write.format(kind).save(where)
        return spark.read.schema(rows.schema).format(kind).load(where)


@register("fn_vector", "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE)), 6) AS norm2, round(list_sum(list_transform(embedding, lambda x, i: x::DOUBLE * i)), 6) AS weighted FROM embeddings")
def fn_vector(spark, sf_dir):
    from pyspark.sql import functions as F

    v = F.transform("embedding", lambda x: x.cast("double"))
    total = lambda a: F.round(F.aggregate(a, F.lit(0.0), lambda s, x: s + x), 6)
    rows = spark.read.parquet(f"{sf_dir}/embeddings.parquet").select("vec_id", v.alias("v"))
    return rows.select("vec_id", total(F.transform("v", lambda x: x * x)).alias("norm2"), total(F.transform("v", lambda x, i: x * (i + 1))).alias("weighted"))


@register("join_cross", "SELECT r_name, n_name FROM region CROSS JOIN nation")
def join_cross(spark, sf_dir):
    """The one product of two tables, both of a fixed few rows."""
    region, nation = (spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in ("region", "nation"))
    return region.select("r_name").crossJoin(nation.select("n_name"))


for _hint in ("broadcast", "merge", "shuffle_hash"):

    @register(f"join_hint_{_hint}", "SELECT s_suppkey, n_name FROM supplier JOIN nation ON s_nationkey = n_nationkey")
    def _(spark, sf_dir, hint=_hint):
        from pyspark.sql import functions as F

        supplier, nation = (spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in ("supplier", "nation"))
        return supplier.join(nation.hint(hint), F.col("s_nationkey") == F.col("n_nationkey")).select("s_suppkey", "n_name")


@register("udtf_decode", f"SELECT term, d, f FROM {Q.counts('turns')}")
def udtf_decode(spark, sf_dir):
    """Blocks of a stored index, read by its data source and decoded by a table function in SQL."""
    from liveindex.functions import udfs
    from liveindex.plans.store import LiveIndex
    from liveindex.scratch import folder
    from liveindex.sources import collections, stored

    index = LiveIndex(spark, folder(spark, "live-index"))
    stream = collections.turns(spark, sf_dir)
    index.insert(stream.where("d <= 100"))
    index.insert(stream.where("d > 100"))
    stored.register(spark)
    udfs.register(spark)
    name = f"blocks_{abs(hash(index.path)) % 10**9}"
    spark.read.format("liveindex").load(index.path).createOrReplaceTempView(name)
    return spark.sql(f"SELECT b.term, p.d, p.f FROM {name} b, LATERAL decode_postings(b.payload, b.first_d, 4) p")
