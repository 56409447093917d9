"""Relational operators around the methods: joins, aggregates, windows, sets, scalars, sources and streams."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from .. import graphs, model
from ..operators import exact, hashing
from ..operators.primitives import sort_all
from ..sources import edges as sources
from ..storage import checkpoint_dir
from ..streaming import edges as streams
from . import sql as _sql

QUERIES: dict = {}
ORACLES: dict[str, str] = {}
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def views(spark, d):
    for t in TABLES:
        graphs.table(spark, d, t).createOrReplaceTempView(t)
    return spark


def both(name: str, text: str, other: str | None = None) -> None:
    """A statement that Spark runs, and what gives the same rows elsewhere (itself if not said)."""
    QUERIES[name] = lambda spark, d: views(spark, d).sql(text)
    ORACLES[name] = other or text


def add(name, query, oracle=None):
    QUERIES[name] = query
    if oracle:
        ORACLES[name] = oracle


both("op_scan_pushdown", "SELECT l_orderkey, l_partkey FROM lineitem WHERE l_quantity > 45 AND l_returnflag = 'R'")
both("op_project_case", "SELECT o_orderkey, CASE WHEN o_totalprice > 200000 THEN 'high' WHEN o_totalprice > 100000 THEN 'mid' ELSE 'low' END AS class FROM orders")
both("op_filter_in_between_like", "SELECT p_partkey FROM part WHERE p_size BETWEEN 5 AND 20 AND p_brand IN ('Brand#11', 'Brand#12', 'Brand#21') AND p_type LIKE '%A%'")
both("op_filter_nulls", "SELECT count(*) AS n, count(lang) AS known, CAST(sum(CASE WHEN lang IS NULL THEN 1 ELSE 0 END) AS BIGINT) AS unknown FROM documents")
both("op_join_broadcast", "SELECT n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name")
both("op_join_sort_merge", "SELECT /*+ MERGE(orders) */ o_orderstatus, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY o_orderstatus")
both("op_join_shuffled_hash", "SELECT /*+ SHUFFLE_HASH(orders) */ o_orderpriority, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY o_orderpriority")
both("op_join_semi", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 300000)")
both("op_join_anti", "SELECT p_partkey FROM part WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_partkey = p_partkey AND l_quantity > 45)")
both("op_join_left", "SELECT c_custkey, count(o_orderkey) AS orders FROM customer LEFT JOIN orders ON o_custkey = c_custkey GROUP BY c_custkey")
both("op_join_full", "SELECT x.k AS a, y.k AS b FROM (SELECT DISTINCT l_partkey AS k FROM lineitem WHERE l_quantity > 49) x FULL OUTER JOIN (SELECT DISTINCT l_partkey AS k FROM lineitem WHERE l_quantity < 2) y ON x.k = y.k")
both("op_join_theta", "SELECT a.n_nationkey AS a, b.n_nationkey AS b FROM nation a JOIN nation b ON a.n_nationkey < b.n_nationkey AND a.n_regionkey <> b.n_regionkey")
both("op_join_self", "SELECT x.l_suppkey AS a, y.l_suppkey AS b, count(*) AS n FROM lineitem x JOIN lineitem y ON x.l_orderkey = y.l_orderkey AND x.l_suppkey < y.l_suppkey GROUP BY x.l_suppkey, y.l_suppkey")
add("op_join_range", graphs.copart30, None)
add("op_join_interval", graphs.corun, None)
both("op_agg_hash", "SELECT l_returnflag, l_linestatus, count(*) AS n, CAST(sum(l_quantity) AS BIGINT) AS quantity FROM lineitem GROUP BY l_returnflag, l_linestatus")
both("op_agg_distinct", "SELECT count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers FROM lineitem")
both("op_agg_filter", "SELECT l_suppkey, count(*) FILTER (WHERE l_returnflag = 'R') AS returned, count(*) AS n FROM lineitem GROUP BY l_suppkey")
both("op_agg_cube", "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
both("op_agg_rollup", "SELECT c_mktsegment, c_nationkey, count(*) AS n FROM customer GROUP BY ROLLUP (c_mktsegment, c_nationkey)")
both("op_agg_grouping_sets", "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())")
both("op_agg_statistics", "SELECT l_returnflag, round(var_samp(l_quantity), 4) AS v, median(l_quantity) AS m FROM lineitem GROUP BY l_returnflag")
both("op_agg_having", "SELECT o_custkey, count(*) AS n FROM orders GROUP BY o_custkey HAVING count(*) > 12")
both(
    "op_pivot",
    "SELECT * FROM (SELECT o_orderstatus AS s, o_orderpriority AS p FROM orders) PIVOT (count(*) FOR s IN ('O' AS o, 'F' AS f, 'P' AS x))",
    "SELECT o_orderpriority AS p, nullif(count(*) FILTER (WHERE o_orderstatus = 'O'), 0) AS o, nullif(count(*) FILTER (WHERE o_orderstatus = 'F'), 0) AS f, nullif(count(*) FILTER (WHERE o_orderstatus = 'P'), 0) AS x FROM orders GROUP BY 1",
)
add("op_unpivot", lambda spark, d: graphs.table(spark, d, "part").select("p_partkey", F.col("p_brand").alias("brand"), F.col("p_type").alias("type")).unpivot("p_partkey", ["brand", "type"], "field", "value"), "SELECT p_partkey, 'brand' AS field, p_brand AS value FROM part UNION ALL SELECT p_partkey, 'type', p_type FROM part")
both("op_window_rank", "SELECT s_suppkey, rank() OVER (PARTITION BY s_nationkey ORDER BY s_acctbal DESC, s_suppkey) AS r, row_number() OVER (ORDER BY s_suppkey) AS n, ntile(4) OVER (ORDER BY s_suppkey) AS q FROM supplier")
both("op_window_lag_lead", "SELECT event_id, lag(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS before, lead(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS after FROM events")
both("op_window_frames", "SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS n, sum(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderkey ROWS UNBOUNDED PRECEDING) AS s FROM orders", "SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS n, CAST(sum(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderkey ROWS UNBOUNDED PRECEDING) AS BIGINT) AS s FROM orders")
both("op_top_k", "SELECT l_suppkey, count(*) AS n FROM lineitem GROUP BY l_suppkey ORDER BY n DESC, l_suppkey LIMIT 10")
both("op_top_k_per_group", "SELECT c_nationkey, c_custkey FROM (SELECT c_nationkey, c_custkey, row_number() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey) AS r FROM customer) t WHERE r <= 3")
both("op_set_union", "SELECT l_suppkey AS k FROM lineitem WHERE l_quantity > 49 UNION SELECT s_suppkey FROM supplier WHERE s_acctbal < 0")
both("op_set_intersect", "SELECT l_partkey AS k FROM lineitem WHERE l_returnflag = 'R' INTERSECT SELECT l_partkey FROM lineitem WHERE l_returnflag = 'A'")
both("op_set_except", "SELECT p_partkey AS k FROM part EXCEPT SELECT l_partkey FROM lineitem WHERE l_returnflag = 'R' AND l_quantity > 30")
both("op_set_except_all", "SELECT l_suppkey AS k FROM lineitem EXCEPT ALL SELECT s_suppkey FROM supplier")
both("op_string", "SELECT c_custkey, upper(trim(c_mktsegment)) AS a, concat_ws('-', c_name, 'x') AS b, length(c_name) AS n, substring(c_name, 1, 4) AS s FROM customer")
both("op_date", "SELECT o_orderkey, CAST(year(o_orderdate) AS BIGINT) AS y, CAST(month(o_orderdate) AS BIGINT) AS m, CAST(datediff(CAST(o_orderdate AS DATE), DATE '1995-01-01') AS BIGINT) AS days FROM orders", "SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) AS days FROM orders")
both("op_math", "SELECT p_partkey, round(ln(p_size), 6) AS l, round(pow(p_size, 0.5), 6) AS r, ceil(p_size / 3.0D) AS c, p_partkey % 7 AS m FROM part", "SELECT p_partkey, round(ln(p_size), 6) AS l, round(pow(p_size, 0.5), 6) AS r, CAST(ceil(p_size / 3.0::DOUBLE) AS BIGINT) AS c, p_partkey % 7 AS m FROM part")
both("op_array", "SELECT o, size(array_intersect(a, b)) AS common, size(a) AS n FROM (SELECT l_orderkey AS o, collect_set(l_suppkey) AS a, collect_set(CASE WHEN l_quantity > 25 THEN l_suppkey END) AS b FROM lineitem GROUP BY l_orderkey)", "SELECT l_orderkey AS o, CAST(count(DISTINCT CASE WHEN l_quantity > 25 THEN l_suppkey END) AS INTEGER) AS common, CAST(count(DISTINCT l_suppkey) AS INTEGER) AS n FROM lineitem GROUP BY l_orderkey")
both("op_higher_order", "SELECT vec_id, round(aggregate(transform(embedding, x -> CAST(x AS DOUBLE) * x), 0.0D, (a, x) -> a + x), 4) AS n FROM embeddings", "SELECT vec_id, round(list_sum([CAST(x AS DOUBLE) * x FOR x IN embedding]), 4) AS n FROM embeddings")
both("op_json", "SELECT event_id, CAST(get_json_object(props, '$.k') AS BIGINT) AS k FROM events", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")
both("op_map", "SELECT element_at(map_from_entries(array(named_struct('k', 'a', 'v', r_regionkey), named_struct('k', 'b', 'v', r_regionkey + 1))), 'b') AS b FROM region", "SELECT r_regionkey + 1 AS b FROM region")
both("op_regex", "SELECT page_id, regexp_extract(url, '^[a-z]+://([^/:]+)', 1) AS host FROM pages")
both("op_scalar_subquery", "SELECT c_custkey FROM customer WHERE c_acctbal > (SELECT avg(c_acctbal) FROM customer) + 4000")
both("op_correlated_subquery", "SELECT o_orderkey FROM orders o WHERE o_totalprice = (SELECT max(o_totalprice) FROM orders i WHERE i.o_custkey = o.o_custkey)")
both("op_recursion", "WITH RECURSIVE r(flag, i, g) AS (SELECT l_returnflag, 0, count(DISTINCT l_linenumber) FROM lineitem GROUP BY l_returnflag UNION ALL SELECT flag, i + 1, g * g FROM r WHERE i < 4) SELECT flag, i, g FROM r")
both("op_dedupe", "SELECT DISTINCT l_orderkey, l_linenumber FROM lineitem")


def _join_asof(spark, d):
    from ..operators.primitives import predecessor

    e = graphs.table(spark, d, "events").where("event_type in ('purchase', 'view')").withColumn("tag", F.when(F.col("event_type") == "purchase", 0).otherwise(1))
    x = predecessor(e, ["ts"], "tag", F.unix_micros(F.col("ts").cast("timestamp")), ["user_id"])
    return x.where("tag = 1 and before is not null").select("event_id", F.col("before").alias("before_us"))


add("op_join_asof", _join_asof, "SELECT v.event_id, epoch_us(p.ts) AS before_us FROM (SELECT * FROM events WHERE event_type = 'view') v ASOF JOIN (SELECT user_id, ts FROM events WHERE event_type = 'purchase') p ON v.user_id = p.user_id AND v.ts >= p.ts")
add("op_sample_stable", lambda spark, d: graphs.table(spark, d, "orders").where(F.pmod(F.xxhash64("o_orderkey"), F.lit(10)) == 0).select("o_orderkey"))
add("op_approx_distinct", lambda spark, d: graphs.table(spark, d, "lineitem").agg(F.approx_count_distinct("l_partkey", 0.02).alias("parts")))
ORACLES["op_join_range"] = _sql.on("copart30", select="SELECT src, dst FROM e")
ORACLES["op_join_interval"] = _sql.on("corun", select="SELECT src, dst FROM e")


def _round_trip(kind):
    def query(spark, d):
        at = f"{checkpoint_dir(spark)}/edges-{kind}-{uuid.uuid4().hex}"
        e = graphs.trade(spark, d)
        if kind == "text":
            e.select(F.concat_ws(" ", "src", "dst").alias("value")).write.mode("overwrite").text(at)
        elif kind == "csv":
            e.write.mode("overwrite").option("header", True).csv(at)
        elif kind == "level":
            sources.write(e.withColumn("level", F.col("src") % 3), at, "parquet", ["level"])
        else:
            sources.write(e, at, kind)
        return sources.read(spark, at, "parquet" if kind == "level" else kind)

    return query


for _kind in ("text", "csv", "json", "orc", "parquet", "level"):
    add(f"src_{_kind}_edges", _round_trip(_kind), _sql.on("trade", select="SELECT src, dst FROM e"))
_customers = lambda spark, d: graphs.table(spark, d, "customer").select("c_custkey")


def _generated(kind, keys=_customers):
    def query(spark, d):
        e = sources.generate_on(keys(spark, d), kind)
        return model.size(e).join(F.broadcast(exact.count_by_rank(e)))

    return query


# a clique takes a column of few values
add("src_generated_clique", _generated("clique", lambda spark, d: graphs.table(spark, d, "lineitem").select("l_quantity")), "SELECT c AS n, CAST(c * (c - 1) // 2 AS BIGINT) AS m, CAST(c * (c - 1) * (c - 2) // 6 AS BIGINT) AS triangles FROM (SELECT count(DISTINCT l_quantity) AS c FROM lineitem)")
for _kind, _n, _m in (("cycle", "c", "c"), ("star", "c", "c - 1"), ("path", "c", "c - 1"), ("grid", "s * s", "2 * s * (s - 1)")):
    add(f"src_generated_{_kind}", _generated(_kind), f"SELECT CAST({_n} AS BIGINT) AS n, CAST({_m} AS BIGINT) AS m, CAST(0 AS BIGINT) AS triangles FROM (SELECT c, CAST(floor(sqrt(c)) AS BIGINT) AS s FROM (SELECT count(DISTINCT c_custkey) AS c FROM customer))")

_stream = lambda spark, d: streams.event_stream(spark, f"{d}/events.parquet")
_DAY = "CAST(floor(epoch(ts) / 86400) * 86400 AS BIGINT)"
add("st_tumbling", lambda spark, d: streams.collect_now(streams.tumbling(_stream(spark, d)), "complete"), f"SELECT {_DAY} AS start_s, event_type, count(*) AS events FROM events GROUP BY ALL")
add("st_sliding", lambda spark, d: streams.collect_now(streams.sliding(_stream(spark, d)), "complete"), f"SELECT s AS start_s, count(*) AS events FROM (SELECT unnest([{_DAY}, {_DAY} - 86400]) AS s FROM events) GROUP BY s")
add("st_dedupe", lambda spark, d: streams.collect_now(streams.without_repeats(_stream(spark, d), ["user_id", "event_type"])).select("user_id", "event_type"), "SELECT DISTINCT user_id, event_type FROM events")
# rows that a watermark of an hour behind the last event has closed
_SESSION = """x AS (SELECT user_id, ts, CASE WHEN ts <= lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 1 HOUR THEN 0 ELSE 1 END AS fresh FROM events),
y AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM x)"""
add("st_session", lambda spark, d: streams.collect_now(streams.sessions(_stream(spark, d)), "append"), f"WITH {_SESSION} SELECT user_id, epoch_us(min(ts)) AS start_us, count(*) AS events FROM y GROUP BY user_id, s HAVING max(ts) + INTERVAL 1 HOUR <= (SELECT max(ts) FROM events) - INTERVAL 1 HOUR")
_HOUR = "CAST(floor(epoch(ts) / 3600) * 3600 AS BIGINT)"
add("st_late", lambda spark, d: streams.collect_now(streams.in_time(_stream(spark, d))), f"SELECT {_HOUR} AS start_s, count(*) AS events FROM events GROUP BY 1 HAVING {_HOUR} + 3600 <= (SELECT epoch(max(ts)) FROM events) - 3600")
add("st_update", lambda spark, d: streams.collect_now(_stream(spark, d).groupBy("event_type").agg(F.count("*").alias("events")), "update", ["event_type"]), "SELECT event_type, count(*) AS events FROM events GROUP BY 1")
add("st_interval_edges", lambda spark, d: model.canonical(streams.collect_now(streams.interval_edges(_stream(spark, d)))), _sql.on("corun", select="SELECT src, dst FROM e"))


def _arrivals(spark, d, files=3):
    at = f"{checkpoint_dir(spark)}/arrivals-{uuid.uuid4().hex}"
    graphs.corun(spark, d).repartition(files, "src").write.mode("overwrite").parquet(at)
    return spark.readStream.schema("src long, dst long").option("maxFilesPerTrigger", 1).parquet(at)


add("st_incremental_tri", lambda spark, d: streams.incremental_triangles(_arrivals(spark, d)), _sql.triangles("corun"))
add("st_stateful_degrees", lambda spark, d: streams.collect_now(streams.degrees_so_far(_arrivals(spark, d)), "update", ["v"]), _sql.on("corun", _sql.ARCS, select="SELECT src AS v, count(*) AS degree FROM a GROUP BY src"))


def _rate(spark, d):
    """The source's numbers, batch by batch, are looked up as events: each that is an event's is found once."""
    s = spark.readStream.format("rate-micro-batch").option("rowsPerBatch", 100).option("numPartitions", 2).load().select("value")
    events = graphs.table(spark, d, "events").select("event_id", "user_id")
    got = streams.collect_now(s.join(events, F.col("value") == F.col("event_id"), "left"))
    n = got.agg(F.count_distinct("value")).first()[0]
    first = F.when(F.col("event_id") < 100, F.col("user_id"))
    found = got.agg(F.count("event_id").alias("found"), F.count_distinct(first).alias("first_users"))
    there = events.where(F.col("event_id").between(0, n - 1)).agg(F.count("*").alias("there"))
    return found.join(F.broadcast(there)).select((F.col("found") == F.col("there")).alias("sound"), F.lit(n % 100 == 0 and n > 0).alias("whole_batches"), "first_users")


add("st_rate_source", _rate, "SELECT true AS sound, true AS whole_batches, count(DISTINCT user_id) AS first_users FROM events WHERE event_id BETWEEN 0 AND 99")


def _edgelist(spark, d):
    at = f"{checkpoint_dir(spark)}/list-{uuid.uuid4().hex}"
    rows = graphs.trade(spark, d).select(F.concat_ws("\t", "src", "dst").alias("value"))
    rows.unionByName(spark.createDataFrame([("# a comment",), ("no numbers",), ("",)], "value string")).write.text(at)
    sources.register(spark)
    return model.canonical(spark.read.format("edgelist").option("path", at).option("parts", 5).load())


add("src_edgelist_edges", _edgelist, _sql.on("trade", select="SELECT src, dst FROM e"))


def _bucketed(spark, d):
    name = f"subcount_edges_{uuid.uuid4().hex}"
    sources.write_bucketed(graphs.trade(spark, d), name, 4)
    return spark.table(name)


add("sink_bucketed", _bucketed, _sql.on("trade", select="SELECT src, dst FROM e"))


def _nothing(spark, d):
    sources.run_only(graphs.trade(spark, d))
    return model.size(graphs.trade(spark, d))


add("sink_noop", _nothing, _sql.on("trade", _sql.ARCS, _sql.DEGREES, select="SELECT count(*) AS n, CAST(sum(deg) // 2 AS BIGINT) AS m FROM g"))
_h = lambda x: hashing.kwise_sql(f"CAST({x} AS BIGINT)", hashing.coefficients(4, 1))
_NUMBERED = "(SELECT row_number() OVER (ORDER BY c_custkey) - 1 AS i, count(*) OVER () AS n FROM (SELECT DISTINCT c_custkey FROM customer WHERE c_custkey IS NOT NULL))"
_MADE = {
    "uniform": f"SELECT {_h('2 * i')} % n AS x, {_h('2 * i + 1')} % n AS y FROM {_NUMBERED}",
    "preferential": f"SELECT i AS x, CAST(floor(i * u * u) AS BIGINT) AS y FROM (SELECT i, {_h('(i * 3 + k)')} / {float(hashing.P31)!r} AS u FROM {_NUMBERED}, (SELECT unnest(range(3)) AS k) WHERE i > 0)",
}
for _kind in _MADE:
    add(f"src_generated_{_kind}", (lambda k: lambda spark, d: sources.generate_on(_customers(spark, d), k, 3))(_kind), f"SELECT DISTINCT CAST(least(x, y) AS BIGINT) AS src, CAST(greatest(x, y) AS BIGINT) AS dst FROM ({_MADE[_kind]}) WHERE x <> y")


def _share(drawn, all_, low, high):
    return drawn.agg(F.count("*").alias("k")).join(F.broadcast(all_.agg(F.count("*").alias("n")))).select((F.col("k") / F.col("n")).between(low, high).alias("within"))


add("op_sample_bernoulli", lambda spark, d: (lambda o: _share(o.sample(0.2, seed=7), o, 0.15, 0.25))(graphs.table(spark, d, "orders")), "SELECT true AS within")
add("op_sample_stratified", lambda spark, d: (lambda o: _share(o.sampleBy("o_orderstatus", {"O": 0.5, "F": 0.0, "P": 0.0}, seed=7), o.where("o_orderstatus = 'O'"), 0.4, 0.6))(graphs.table(spark, d, "orders")), "SELECT true AS within")
add("op_sort_all", lambda spark, d: sort_all(graphs.table(spark, d, "orders").select("o_custkey", "o_orderkey"), ["o_custkey", "o_orderkey"]).withColumn("id", F.monotonically_increasing_id()).groupBy("o_custkey").agg(F.min_by("o_orderkey", "id").alias("first"), F.max_by("o_orderkey", "id").alias("last")), "SELECT o_custkey, min(o_orderkey) AS first, max(o_orderkey) AS last FROM orders GROUP BY 1")
