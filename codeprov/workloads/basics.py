"""Surrounding operators on the given tables: every line of the inventory has a query and its SQL."""

from __future__ import annotations


from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from codeprov.operators import joins
from codeprov.session import cut_lineage, shared_folder, table

QUERIES, SQL = {}, {}


def _op(name: str, sql: str | None):
    def add(f):
        QUERIES[f"O_{name}"] = f
        if sql is not None:
            SQL[f"O_{name}"] = sql
        return f

    return add


def _t(name):
    return lambda spark, sf: table(spark, sf, name)


orders, lineitem, customer, supplier, nation, region, part, events, documents, benchmark, pages, labels, embeddings, conversations = map(_t, "orders lineitem customer supplier nation region part events documents benchmark pages labels embeddings conversations".split())

_COUNTS = " UNION ALL ".join(f"SELECT '{t}' AS name, count(*) AS n FROM {t}" for t in "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split())


@_op("scan_parquet", _COUNTS)
def scan_parquet(spark, sf):
    from functools import reduce

    names = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
    return reduce(DataFrame.unionByName, [table(spark, sf, t).agg(F.count("*").alias("n")).select(F.lit(t).alias("name"), "n") for t in names])


def _round_trip(spark, df: DataFrame, kind: str, **options) -> DataFrame:
    """Written to the shared folder if there is one, and read again with the schema known."""
    import uuid

    path = f"{shared_folder(spark)}/{kind}-{uuid.uuid4().hex}"
    df.write.format(kind).options(**options).save(path)
    return spark.read.schema(df.schema).options(**options).format(kind).load(path)


_NATION = "SELECT n_nationkey, n_name, n_regionkey FROM nation"


@_op("scan_json", _NATION)
def scan_json(spark, sf):
    return _round_trip(spark, nation(spark, sf).select("n_nationkey", "n_name", "n_regionkey"), "json")


@_op("scan_csv", _NATION)
def scan_csv(spark, sf):
    return _round_trip(spark, nation(spark, sf).select("n_nationkey", "n_name", "n_regionkey"), "csv", header="true")


@_op("scan_orc", _NATION)
def scan_orc(spark, sf):
    return _round_trip(spark, nation(spark, sf).select("n_nationkey", "n_name", "n_regionkey"), "orc")


@_op("scan_rows", "SELECT c_custkey AS id, c_name AS s FROM customer")
def scan_rows(spark, sf):
    """Python rows as a source, here those that the tasks make of a table's rows."""
    rows = customer(spark, sf).select("c_custkey", "c_name").rdd.map(tuple)
    return spark.createDataFrame(rows, "id long, s string")


@_op("sink_roundtrip", "SELECT year(o_orderdate)::BIGINT AS y, count(*) AS n, round(sum(o_totalprice), 2) AS total FROM orders GROUP BY ALL")
def sink_roundtrip(spark, sf):
    import uuid

    path = f"{shared_folder(spark)}/by-year-{uuid.uuid4().hex}"
    orders(spark, sf).select("o_orderkey", "o_totalprice", F.year("o_orderdate").alias("y")).repartition("y").sortWithinPartitions("o_orderkey").write.partitionBy("y").parquet(path)
    return spark.read.parquet(path).groupBy(F.col("y").cast("long").alias("y")).agg(F.count("*").alias("n"), F.round(F.sum("o_totalprice"), 2).alias("total"))


@_op("project", "SELECT l_orderkey, l_linenumber, round(l_extendedprice * (1 - l_discount), 4) AS revenue, l_quantity::INT AS quantity FROM lineitem")
def project(spark, sf):
    return lineitem(spark, sf).select("l_orderkey", "l_linenumber", F.round(F.col("l_extendedprice") * (1 - F.col("l_discount")), 4).alias("revenue"), F.col("l_quantity").try_cast("int").alias("quantity"))


@_op("filter", "SELECT l_orderkey, l_linenumber FROM lineitem WHERE l_shipdate BETWEEN TIMESTAMP '1996-01-01' AND TIMESTAMP '1998-01-01' AND l_quantity < 24 AND l_returnflag IN ('R', 'A')")
def filter_(spark, sf):
    return lineitem(spark, sf).where("l_shipdate BETWEEN TIMESTAMP_NTZ'1996-01-01' AND TIMESTAMP_NTZ'1998-01-01' AND l_quantity < 24 AND l_returnflag IN ('R', 'A')").select("l_orderkey", "l_linenumber")


@_op("case", "SELECT o_orderkey, CASE WHEN o_totalprice > 300000 THEN 'high' WHEN o_totalprice > 100000 THEN 'middle' ELSE 'low' END AS band, o_orderpriority IS NOT DISTINCT FROM '1-URGENT' AS urgent FROM orders")
def case(spark, sf):
    p = F.col("o_totalprice")
    return orders(spark, sf).select("o_orderkey", F.when(p > 300000, "high").when(p > 100000, "middle").otherwise("low").alias("band"), F.col("o_orderpriority").eqNullSafe("1-URGENT").alias("urgent"))


_WORDS = r"list_filter(regexp_split_to_array(lower(text), '[^\p{L}\p{N}]+'), lambda w: w <> '')"


def _words(c="text"):
    return F.filter(F.split(F.lower(F.col(c)), r"[^\p{L}\p{N}]+"), lambda w: w != "")


@_op("explode", f"SELECT word, count(*) AS n FROM (SELECT unnest({_WORDS}) AS word FROM documents) GROUP BY ALL")
def explode(spark, sf):
    return documents(spark, sf).select(F.explode(_words()).alias("word")).groupBy("word").agg(F.count("*").alias("n"))


@_op("posexplode", f"SELECT item_id, generate_subscripts({_WORDS}, 1) - 1 AS pos, unnest({_WORDS}) AS word FROM benchmark")
def posexplode(spark, sf):
    return benchmark(spark, sf).select("item_id", F.posexplode(_words()).alias("pos", "word")).withColumn("pos", F.col("pos").cast("long"))


@_op("lateral", "SELECT o_orderkey, l_partkey, l_extendedprice FROM orders, LATERAL (SELECT l_partkey, l_extendedprice FROM lineitem WHERE l_orderkey = o_orderkey ORDER BY l_extendedprice DESC, l_partkey LIMIT 1)")
def lateral(spark, sf):
    top = lineitem(spark, sf).groupBy("l_orderkey").agg(F.max_by(F.struct("l_partkey", "l_extendedprice"), F.struct("l_extendedprice", -F.col("l_partkey"))).alias("t"))
    return orders(spark, sf).join(top, F.col("o_orderkey") == F.col("l_orderkey")).select("o_orderkey", "t.l_partkey", "t.l_extendedprice")


@_op("join_inner", "SELECT o_orderpriority, count(*) AS n, round(sum(l_extendedprice), 2) AS total FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY ALL")
def join_inner(spark, sf):
    return orders(spark, sf).join(lineitem(spark, sf), F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderpriority").agg(F.count("*").alias("n"), F.round(F.sum("l_extendedprice"), 2).alias("total"))


@_op("join_broadcast", "SELECT s_suppkey, n_name, r_name FROM supplier JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey")
def join_broadcast(spark, sf):
    small = F.broadcast(nation(spark, sf).join(F.broadcast(region(spark, sf)), F.col("n_regionkey") == F.col("r_regionkey")))
    return supplier(spark, sf).join(small, F.col("s_nationkey") == F.col("n_nationkey")).select("s_suppkey", "n_name", "r_name")


@_op("join_left", "SELECT c_custkey, count(o_orderkey) AS n FROM customer LEFT JOIN orders ON c_custkey = o_custkey GROUP BY ALL")
def join_left(spark, sf):
    per = orders(spark, sf).groupBy("o_custkey").agg(F.count("*").alias("n"))
    return customer(spark, sf).join(per, F.col("c_custkey") == F.col("o_custkey"), "left").select("c_custkey", F.coalesce("n", F.lit(0)).alias("n"))


@_op("join_full", "SELECT doc_id, quality, lang FROM labels FULL JOIN documents USING (doc_id)")
def join_full(spark, sf):
    return labels(spark, sf).select("doc_id", "quality").join(documents(spark, sf).select("doc_id", "lang"), "doc_id", "full")


@_op("semi", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")
def semi(spark, sf):
    return customer(spark, sf).join(orders(spark, sf), F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey")


@_op("anti", "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderstatus = 'O')")
def anti(spark, sf):
    return customer(spark, sf).join(orders(spark, sf).where("o_orderstatus = 'O'"), F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey")


@_op("exists_or", "SELECT p_partkey FROM part WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_partkey = p_partkey AND l_discount > 0.09) OR EXISTS (SELECT 1 FROM lineitem WHERE l_partkey = p_partkey AND l_returnflag = 'R' AND l_quantity < 3)")
def exists_or(spark, sf):
    hit = lineitem(spark, sf).where("l_discount > 0.09 OR (l_returnflag = 'R' AND l_quantity < 3)")
    return part(spark, sf).join(hit, F.col("p_partkey") == F.col("l_partkey"), "left_semi").select("p_partkey")


@_op("theta", "SELECT a.s_suppkey AS a, b.s_suppkey AS b FROM supplier a JOIN supplier b ON a.s_nationkey = b.s_nationkey AND a.s_acctbal > b.s_acctbal + 500")
def theta(spark, sf):
    a = supplier(spark, sf).select(F.col("s_suppkey").alias("a"), F.col("s_nationkey").alias("n"), F.col("s_acctbal").alias("x"))
    b = supplier(spark, sf).select(F.col("s_suppkey").alias("b"), F.col("s_nationkey").alias("n"), F.col("s_acctbal").alias("y"))
    return a.join(b, (a["n"] == b["n"]) & (a["x"] > b["y"] + 500)).select("a", "b")


@_op("interval_join", "SELECT a.event_id AS event_id, b.event_id AS event_id_r FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def interval_join(spark, sf):
    e = events(spark, sf).select("event_id", "user_id", "ts")
    return joins.interval(e, e, "user_id", "ts", 3600).select("event_id", "event_id_r")


@_op("asof", "SELECT p.event_id, v.event_id AS last_view FROM (SELECT * FROM events WHERE event_type = 'purchase') p ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'view') v ON p.user_id = v.user_id AND p.ts >= v.ts")
def asof(spark, sf):
    e = events(spark, sf).select("event_id", "user_id", "ts", "event_type")
    return joins.as_of(e.where("event_type = 'purchase'"), e.where("event_type = 'view'"), "user_id", "ts", "event_id", "last_view").select("event_id", "last_view")


@_op("self_join", "SELECT a.s_suppkey AS a, b.s_suppkey AS b FROM supplier a JOIN supplier b ON a.s_nationkey = b.s_nationkey AND a.s_suppkey < b.s_suppkey")
def self_join(spark, sf):
    s = supplier(spark, sf)
    return s.alias("a").join(s.alias("b"), F.expr("a.s_nationkey = b.s_nationkey AND a.s_suppkey < b.s_suppkey")).select(F.col("a.s_suppkey").alias("a"), F.col("b.s_suppkey").alias("b"))


@_op("agg", "SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS qty, round(avg(l_discount), 6) AS disc, count(*) FILTER (l_tax > 0.05) AS taxed, bool_and(l_quantity > 0) AS positive FROM lineitem GROUP BY ALL")
def agg(spark, sf):
    return lineitem(spark, sf).groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("qty"), F.round(F.avg("l_discount"), 6).alias("disc"), F.count_if(F.col("l_tax") > 0.05).alias("taxed"), F.bool_and(F.col("l_quantity") > 0).alias("positive"))


@_op("minmax_by", "SELECT o_custkey, arg_max(o_orderkey, (o_totalprice, o_orderkey)) AS dearest, arg_min(o_orderkey, (o_totalprice, o_orderkey)) AS cheapest FROM orders GROUP BY ALL")
def minmax_by(spark, sf):
    k = F.struct("o_totalprice", "o_orderkey")
    return orders(spark, sf).groupBy("o_custkey").agg(F.max_by("o_orderkey", k).alias("dearest"), F.min_by("o_orderkey", k).alias("cheapest"))


@_op("percentile", "SELECT l_returnflag, quantile_cont(l_quantity, 0.5) AS median, round(quantile_cont(l_extendedprice, 0.9), 4) AS p90 FROM lineitem GROUP BY ALL")
def percentile(spark, sf):
    return lineitem(spark, sf).groupBy("l_returnflag").agg(F.percentile("l_quantity", 0.5).alias("median"), F.round(F.percentile("l_extendedprice", 0.9), 4).alias("p90"))


@_op("statistics", "SELECT l_shipmode_key, round(corr(l_quantity, l_extendedprice), 6) AS r, round(stddev_samp(l_discount), 6) AS sd FROM (SELECT *, l_linenumber AS l_shipmode_key FROM lineitem) GROUP BY ALL")
def statistics(spark, sf):
    return lineitem(spark, sf).groupBy(F.col("l_linenumber").alias("l_shipmode_key")).agg(F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("r"), F.round(F.stddev_samp("l_discount"), 6).alias("sd"))


@_op("agg_distinct", "SELECT o_orderstatus, count(DISTINCT o_custkey) AS customers, count(DISTINCT o_orderpriority) AS priorities FROM orders GROUP BY ALL")
def agg_distinct(spark, sf):
    return orders(spark, sf).groupBy("o_orderstatus").agg(F.count_distinct("o_custkey").alias("customers"), F.count_distinct("o_orderpriority").alias("priorities"))


@_op("approx", "SELECT true AS distinct_close, true AS median_close, true AS sketch_close")
def approx(spark, sf):
    a = lineitem(spark, sf).agg(F.approx_count_distinct("l_partkey", 0.02).alias("ad"), F.count_distinct("l_partkey").alias("d"), F.percentile_approx("l_extendedprice", 0.5, 10000).alias("am"), F.percentile("l_extendedprice", 0.5).alias("m"), F.hll_sketch_estimate(F.hll_sketch_agg("l_partkey", 14)).alias("h"))
    close = lambda x, y: F.abs(F.col(x) - F.col(y)) <= 0.1 * F.col(y)
    return a.select(close("ad", "d").alias("distinct_close"), close("am", "m").alias("median_close"), close("h", "d").alias("sketch_close"))


_CUBE = "FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"


def _located(spark, sf):
    return customer(spark, sf).join(F.broadcast(nation(spark, sf)), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(region(spark, sf)), F.col("n_regionkey") == F.col("r_regionkey"))


@_op("rollup", f"SELECT r_name, n_name, grouping(r_name, n_name)::BIGINT AS g, count(*) AS n {_CUBE} GROUP BY ROLLUP (r_name, n_name)")
def rollup(spark, sf):
    return _located(spark, sf).rollup("r_name", "n_name").agg(F.grouping_id().cast("long").alias("g"), F.count("*").alias("n"))


@_op("cube", f"SELECT r_name, c_mktsegment, grouping(r_name, c_mktsegment)::BIGINT AS g, count(*) AS n {_CUBE} GROUP BY CUBE (r_name, c_mktsegment)")
def cube(spark, sf):
    return _located(spark, sf).cube("r_name", "c_mktsegment").agg(F.grouping_id().cast("long").alias("g"), F.count("*").alias("n"))


@_op("gsets", f"SELECT r_name, c_mktsegment, count(*) AS n {_CUBE} GROUP BY GROUPING SETS ((r_name), (c_mktsegment), ())")
def gsets(spark, sf):
    return _located(spark, sf).groupingSets([["r_name"], ["c_mktsegment"], []], "r_name", "c_mktsegment").agg(F.count("*").alias("n"))


@_op("pivot", "SELECT user_id, count(*) FILTER (event_type = 'view') AS view, count(*) FILTER (event_type = 'purchase') AS purchase FROM events GROUP BY ALL")
def pivot(spark, sf):
    return events(spark, sf).groupBy("user_id").pivot("event_type", ["view", "purchase"]).count().na.fill(0)


@_op("unpivot", "SELECT s_suppkey, 'nation' AS what, s_nationkey::DOUBLE AS v FROM supplier UNION ALL SELECT s_suppkey, 'balance', s_acctbal FROM supplier")
def unpivot(spark, sf):
    s = supplier(spark, sf).select("s_suppkey", F.col("s_nationkey").cast("double").alias("nation"), F.col("s_acctbal").alias("balance"))
    return s.unpivot("s_suppkey", ["nation", "balance"], "what", "v")


@_op("win_rank", "SELECT o_orderkey, row_number() OVER w AS rn, rank() OVER v AS rk, dense_rank() OVER v AS dr, ntile(4) OVER w AS q, round(percent_rank() OVER v, 6) AS pr, round(cume_dist() OVER v, 6) AS cd FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey), v AS (PARTITION BY o_custkey ORDER BY o_orderpriority)")
def win_rank(spark, sf):
    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    v = Window.partitionBy("o_custkey").orderBy("o_orderpriority")
    long = lambda c: c.cast("long")
    return orders(spark, sf).select("o_orderkey", long(F.row_number().over(w)).alias("rn"), long(F.rank().over(v)).alias("rk"), long(F.dense_rank().over(v)).alias("dr"), long(F.ntile(4).over(w)).alias("q"), F.round(F.percent_rank().over(v), 6).alias("pr"), F.round(F.cume_dist().over(v), 6).alias("cd"))


@_op("win_lag", "SELECT event_id, lag(event_id) OVER w AS before, lead(event_id) OVER w AS after, first_value(event_id) OVER w AS first, nth_value(event_id, 2) OVER w AS second FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def win_lag(spark, sf):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return events(spark, sf).select("event_id", F.lag("event_id").over(w).alias("before"), F.lead("event_id").over(w).alias("after"), F.first("event_id").over(w).alias("first"), F.nth_value("event_id", 2).over(w).alias("second"))


@_op("win_rows", "SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY ts, event_id), 4) AS running, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 4) AS moving FROM events")
def win_rows(spark, sf):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return events(spark, sf).select("event_id", F.round(F.sum("value").over(w.rowsBetween(Window.unboundedPreceding, 0)), 4).alias("running"), F.round(F.avg("value").over(w.rowsBetween(-2, 0)), 4).alias("moving"))


@_op("win_range", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch(ts)::BIGINT RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS n FROM (SELECT event_id, user_id, date_trunc('second', ts) AS ts FROM events)")
def win_range(spark, sf):
    e = events(spark, sf).withColumn("s", F.unix_timestamp(F.date_trunc("second", "ts").cast("timestamp")))
    return e.select("event_id", F.count("*").over(Window.partitionBy("user_id").orderBy("s").rangeBetween(-3600, 0)).alias("n"))


@_op("topk", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 25")
def topk(spark, sf):
    return orders(spark, sf).orderBy(F.desc("o_totalprice"), "o_orderkey").limit(25).select("o_orderkey", "o_totalprice")


@_op("topk_group", "SELECT o_orderpriority, o_orderkey FROM orders QUALIFY row_number() OVER (PARTITION BY o_orderpriority ORDER BY o_totalprice DESC, o_orderkey) <= 3")
def topk_group(spark, sf):
    w = Window.partitionBy("o_orderpriority").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return orders(spark, sf).withColumn("r", F.row_number().over(w)).where("r <= 3").select("o_orderpriority", "o_orderkey")


@_op("offset", "SELECT p_partkey FROM part ORDER BY p_retailprice DESC NULLS LAST, p_partkey LIMIT 20 OFFSET 10")
def offset(spark, sf):
    return part(spark, sf).orderBy(F.desc_nulls_last("p_retailprice"), "p_partkey").offset(10).limit(20).select("p_partkey")


@_op("union", "SELECT c_nationkey AS k FROM customer UNION SELECT s_nationkey FROM supplier UNION ALL SELECT n_nationkey FROM nation")
def union(spark, sf):
    a = customer(spark, sf).select(F.col("c_nationkey").alias("k")).union(supplier(spark, sf).select("s_nationkey")).distinct()
    return a.unionByName(nation(spark, sf).select(F.col("n_nationkey").alias("k")))


@_op("intersect", "SELECT c_nationkey AS k FROM customer INTERSECT ALL SELECT s_nationkey FROM supplier")
def intersect(spark, sf):
    return customer(spark, sf).select(F.col("c_nationkey").alias("k")).intersectAll(supplier(spark, sf).select("s_nationkey"))


@_op("except", "SELECT c_nationkey AS k FROM customer EXCEPT ALL SELECT s_nationkey FROM supplier")
def except_(spark, sf):
    return customer(spark, sf).select(F.col("c_nationkey").alias("k")).exceptAll(supplier(spark, sf).select("s_nationkey"))


@_op("scalar_subq", "SELECT o_orderkey FROM orders o WHERE o_totalprice > (SELECT avg(o_totalprice) FROM orders i WHERE i.o_custkey = o.o_custkey) + 1000")
def scalar_subq(spark, sf):
    o = orders(spark, sf)
    mean = o.groupBy(F.col("o_custkey").alias("k")).agg(F.avg("o_totalprice").alias("m"))
    return o.join(mean, o["o_custkey"] == mean["k"]).where("o_totalprice > m + 1000").select("o_orderkey")


@_op("in_subq", "SELECT p_partkey FROM part WHERE p_partkey IN (SELECT l_partkey FROM lineitem WHERE l_quantity > 49)")
def in_subq(spark, sf):
    return part(spark, sf).join(lineitem(spark, sf).where("l_quantity > 49"), F.col("p_partkey") == F.col("l_partkey"), "left_semi").select("p_partkey")


_CTE = "WITH big AS (SELECT o_custkey, sum(o_totalprice) AS total FROM orders GROUP BY o_custkey) SELECT c_mktsegment, count(*) AS n FROM big JOIN customer ON c_custkey = o_custkey WHERE total > 500000 GROUP BY c_mktsegment"


@_op("cte", _CTE)
def cte(spark, sf):
    return spark.sql(_CTE.replace("FROM orders", "FROM {orders}").replace("JOIN customer", "JOIN {customer}"), orders=orders(spark, sf), customer=customer(spark, sf))


_CHAIN = """SELECT event_id, user_id, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS k FROM {e}"""
_DEPTH = "WITH RECURSIVE c AS ({chain}), r(user_id, k, depth) AS (SELECT user_id, k, 1 FROM c WHERE k = 1 UNION ALL SELECT c.user_id, c.k, r.depth + 1 FROM r JOIN c ON c.user_id = r.user_id AND c.k = r.k + 1) SELECT user_id, max(depth)::BIGINT AS depth FROM r GROUP BY user_id"
#: The same rows of ``r`` in fewer steps: an event is reached from ``back``, with 15 more after it, so a chain of n events takes log16(n) steps.
_REACHED = "WITH RECURSIVE r(user_id, k, depth) AS (SELECT user_id, k, CAST(1 AS BIGINT) FROM {c} WHERE k = 1 UNION ALL SELECT c.user_id, c.k, r.depth + c.k - r.k FROM r JOIN {c} c ON c.user_id = r.user_id AND c.back = r.k) SELECT user_id, max(depth) AS depth FROM (SELECT user_id, depth FROM r LIMIT ALL) GROUP BY user_id"


@_op("recursive", _DEPTH.format(chain=_CHAIN.format(e="events")))
def recursive(spark, sf):
    """The chain is written once, as every step reads it; LIMIT ALL takes away Spark's limit of a million rows in all steps."""
    chain = cut_lineage(spark.sql(f"SELECT user_id, CAST(k AS BIGINT) AS k, IF(k > 1, (k - 2) DIV 16 + 1, 0) AS back FROM ({_CHAIN})", e=events(spark, sf)))
    return spark.sql(_REACHED, c=chain)


@_op("string", r"SELECT item_id, lower(substr(text, 1, 10)) AS head, length(text)::BIGINT AS n, lpad(item_id::VARCHAR, 6, '0') AS padded, reverse(substr(text, 1, 5)) AS back, instr(text, 'the')::BIGINT AS at, md5(text) AS md5, sha256(text) AS sha, translate(substr(text, 1, 20), 'aeo', '430') AS leet, concat_ws('-', 'i', item_id::VARCHAR) AS name FROM benchmark")
def string(spark, sf):
    t, i = F.col("text"), F.col("item_id").cast("string")
    return benchmark(spark, sf).select("item_id", F.lower(F.substring(t, 1, 10)).alias("head"), F.length(t).cast("long").alias("n"), F.lpad(i, 6, "0").alias("padded"), F.reverse(F.substring(t, 1, 5)).alias("back"), F.instr(t, "the").cast("long").alias("at"), F.md5(t.cast("binary")).alias("md5"), F.sha2(t, 256).alias("sha"), F.translate(F.substring(t, 1, 20), "aeo", "430").alias("leet"), F.concat_ws("-", F.lit("i"), i).alias("name"))


@_op("regex", r"SELECT doc_id, regexp_extract(text, '([A-Z][a-z]+)', 1) AS word, len(regexp_extract_all(text, '[0-9]+'))::BIGINT AS numbers, regexp_matches(text, '@[a-z]') AS mail, length(regexp_replace(text, '\s+', ' ', 'g'))::BIGINT AS n FROM documents")
def regex(spark, sf):
    t = F.col("text")
    return documents(spark, sf).select("doc_id", F.regexp_extract(t, "([A-Z][a-z]+)", 1).alias("word"), F.size(F.regexp_extract_all(t, F.lit("[0-9]+"), F.lit(0))).cast("long").alias("numbers"), t.rlike("@[a-z]").alias("mail"), F.length(F.regexp_replace(t, r"\s+", " ")).cast("long").alias("n"))


@_op("date", "SELECT o_orderkey, date_trunc('month', o_orderdate)::VARCHAR AS month, date_diff('day', DATE '1992-01-01', o_orderdate::DATE)::BIGINT AS days, quarter(o_orderdate)::BIGINT AS q, (o_orderdate + INTERVAL 30 DAY)::VARCHAR AS due, epoch(o_orderdate)::BIGINT AS s FROM orders")
def date(spark, sf):
    d = F.col("o_orderdate")
    text = lambda c: F.date_format(c, "yyyy-MM-dd HH:mm:ss")
    return orders(spark, sf).select("o_orderkey", text(F.date_trunc("month", d)).alias("month"), F.datediff(d, F.lit("1992-01-01")).cast("long").alias("days"), F.quarter(d).cast("long").alias("q"), text(d + F.expr("INTERVAL '30' DAY")).alias("due"), F.unix_timestamp(d.cast("timestamp")).alias("s"))


SQL["O_date"] = SQL["O_date"].replace("date_trunc('month', o_orderdate)::VARCHAR", "strftime(date_trunc('month', o_orderdate), '%Y-%m-%d %H:%M:%S')").replace("(o_orderdate + INTERVAL 30 DAY)::VARCHAR", "strftime(o_orderdate + INTERVAL 30 DAY, '%Y-%m-%d %H:%M:%S')")


@_op("math", "SELECT l_orderkey, l_linenumber, (l_partkey % 7)::BIGINT AS m, (l_partkey & 255)::BIGINT AS b, bit_count(l_partkey)::BIGINT AS ones, round(ln(l_extendedprice), 6) AS l, round(sqrt(l_quantity), 6) AS r, greatest(l_tax, l_discount) AS g, round(l_tax / nullif(l_discount, 0), 6) AS q FROM lineitem")
def math_(spark, sf):
    p = F.col("l_partkey")
    return lineitem(spark, sf).select("l_orderkey", "l_linenumber", F.pmod(p, F.lit(7)).alias("m"), p.bitwiseAND(255).alias("b"), F.bit_count(p).cast("long").alias("ones"), F.round(F.ln("l_extendedprice"), 6).alias("l"), F.round(F.sqrt("l_quantity"), 6).alias("r"), F.greatest("l_tax", "l_discount").alias("g"), F.round(F.try_divide("l_tax", "l_discount"), 6).alias("q"))


@_op("array", f"WITH w AS (SELECT doc_id, {_WORDS} AS w FROM documents) SELECT doc_id, len(w)::BIGINT AS n, len(list_distinct(w))::BIGINT AS d, len(list_filter(w, lambda x: length(x) > 5))::BIGINT AS long_words, list_contains(w, 'the') AS has_the, list_max(list_transform(w, lambda x: length(x)))::BIGINT AS longest, len(list_intersect(w, ['the', 'der', 'la', 'of']))::BIGINT AS known FROM w")
def array(spark, sf):
    w = documents(spark, sf).select("doc_id", _words().alias("w"))
    long = lambda c: c.cast("long")
    return w.select("doc_id", long(F.size("w")).alias("n"), long(F.size(F.array_distinct("w"))).alias("d"), long(F.size(F.filter("w", lambda x: F.length(x) > 5))).alias("long_words"), F.array_contains("w", "the").alias("has_the"), long(F.array_max(F.transform("w", lambda x: F.length(x)))).alias("longest"), long(F.size(F.array_intersect("w", F.array(*map(F.lit, ["the", "der", "la", "of"]))))).alias("known"))


@_op("vector", "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x)), 4) AS norm2, round(list_max(embedding)::DOUBLE, 5) AS top FROM embeddings")
def vector(spark, sf):
    e = F.transform("embedding", lambda x: x.cast("double"))
    return embeddings(spark, sf).select("vec_id", F.round(F.aggregate(F.zip_with(e, e, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x), 4).alias("norm2"), F.round(F.array_max(e), 5).alias("top"))


@_op("map", "SELECT event_id, event_type AS kind, (value * 2)::DOUBLE AS twice FROM events")
def map_(spark, sf):
    m = F.map_from_entries(F.array(F.struct(F.lit("v").alias("k"), F.col("value").alias("v")), F.struct(F.lit("w").alias("k"), (F.col("value") * 2).alias("v"))))
    e = events(spark, sf).select("event_id", m.alias("m"), F.named_struct(F.lit("kind"), F.col("event_type")).alias("s"))
    return e.select("event_id", "s.kind", F.element_at(F.transform_values("m", lambda k, v: v), "w").alias("twice"))


@_op("json", "SELECT event_id, json_extract_string(props, '$.k')::BIGINT AS k, json_extract_string(props, '$.missing') AS missing FROM events")
def json_(spark, sf):
    p = F.from_json("props", "k bigint")
    return events(spark, sf).select("event_id", p["k"].alias("k"), F.get_json_object("props", "$.missing").alias("missing"))


@_op("variant", "SELECT event_id, json_extract_string(props, '$.k')::BIGINT AS k FROM events")
def variant(spark, sf):
    return events(spark, sf).select("event_id", F.try_variant_get(F.try_parse_json("props"), "$.k", "bigint").alias("k"))


@_op("html", r"SELECT page_id, regexp_extract(html, '<title>([^<]*)</title>', 1) AS title, len(regexp_extract_all(html, '<li>'))::BIGINT AS items, length(regexp_replace(html, '<[^>]*>', '', 'g'))::BIGINT AS n FROM pages")
def html(spark, sf):
    h = F.col("html")
    return pages(spark, sf).select("page_id", F.regexp_extract(h, "<title>([^<]*)</title>", 1).alias("title"), F.size(F.regexp_extract_all(h, F.lit("<li>"), F.lit(0))).cast("long").alias("items"), F.length(F.regexp_replace(h, "<[^>]*>", "")).cast("long").alias("n"))


@_op("url", r"SELECT page_id, regexp_extract(url, '^[a-z]+://([^/?#:]+)', 1) AS host, regexp_extract(url, '^[a-z]+://[^/?#]+([^?#]*)', 1) AS path FROM pages")
def url(spark, sf):
    return pages(spark, sf).select("page_id", F.try_parse_url("url", F.lit("HOST")).alias("host"), F.try_parse_url("url", F.lit("PATH")).alias("path"))


@_op("sample_hash", "SELECT doc_id FROM documents WHERE CAST('0x' || substr(md5(doc_id::VARCHAR), 1, 4) AS INT) % 10 = 0")
def sample_hash(spark, sf):
    return documents(spark, sf).where(F.conv(F.substring(F.md5(F.col("doc_id").cast("string").cast("binary")), 1, 4), 16, 10).cast("int") % 10 == 0).select("doc_id")


@_op("udf", "SELECT a.n_name AS a, b.r_name AS b, levenshtein(a.n_name, b.r_name)::BIGINT AS d FROM nation a, region b")
def udf(spark, sf):
    from codeprov.functions.register import edit_distance

    return nation(spark, sf).crossJoin(F.broadcast(region(spark, sf))).select(F.col("n_name").alias("a"), F.col("r_name").alias("b"), edit_distance("n_name", "r_name").alias("d"))


@_op("udaf", "SELECT o_orderpriority, round(corr(o_totalprice, o_custkey), 6) AS r FROM orders GROUP BY ALL")
def udaf(spark, sf):
    from codeprov.functions.register import correlation

    return orders(spark, sf).groupBy("o_orderpriority").agg(F.round(correlation("o_totalprice", F.col("o_custkey").cast("double")), 6).alias("r"))


@_op("udtf", f"SELECT item_id, generate_subscripts({_WORDS}, 1)::BIGINT - 1 AS pos, unnest({_WORDS}) AS token FROM benchmark")
def udtf(spark, sf):
    from codeprov.functions.register import register

    register(spark)
    benchmark(spark, sf).createOrReplaceTempView("codeprov_items")
    return spark.sql("SELECT item_id, t.pos, t.token FROM codeprov_items, LATERAL fp_tokens(text) t")


@_op("grouped_map", "SELECT user_id, string_agg(event_type, '>' ORDER BY ts, event_id) AS path FROM events GROUP BY ALL")
def grouped_map(spark, sf):
    def path(pdf):
        pdf = pdf.sort_values(["ts", "event_id"])
        return pdf.iloc[:1][["user_id"]].assign(path=">".join(pdf["event_type"]))

    return events(spark, sf).select("user_id", "ts", "event_id", "event_type").groupBy("user_id").applyInPandas(path, "user_id long, path string")
