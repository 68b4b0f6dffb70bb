"""The relational surface around the methods: scans, joins, aggregates, windows, sets and functions, each with its SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql import Window as W

from ..functions import vectors
from ..functions.hashing import split_name
from ..schemas import PROPS, TABLES
from ..sources import sinks
from ..sources.tables import read_all, read_table, read_with_schema
from ..timing import trace as tr
from .common import rounded, trace, trace_sql

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None, digits: int = 8):
    def put(f):
        QUERIES[name] = lambda spark, sf_dir: rounded(f(spark, sf_dir), digits)
        if sql:
            ORACLES[name] = sql
        return f

    return put


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    return read_table(spark, sf_dir, name, list(columns) or None)


# ---- sources ---------------------------------------------------------------------------------------------------

@query("scan_validated", " UNION ALL ".join(f"SELECT '{t}' AS table_name, count(*)::BIGINT AS n FROM {t}" for t in TABLES))
def _(spark, sf_dir):
    out = None
    for name, df in read_all(spark, sf_dir).items():
        one = df.agg(F.count("*").alias("n")).select(F.lit(name).alias("table_name"), "n")
        out = one if out is None else out.unionByName(one)
    return out


@query("scan_csv_json_roundtrip", "SELECT 'csv' AS fmt, n_nationkey::BIGINT AS id, n_name AS text FROM nation UNION ALL SELECT 'json', event_id, event_type || ':' || user_id FROM events UNION ALL SELECT 'orc', r_regionkey::BIGINT, r_name FROM region")
def _(spark, sf_dir):
    path = sinks.scratch_path(spark, "formats")
    table(spark, sf_dir, "nation").write.option("header", True).csv(f"{path}/csv")
    events = table(spark, sf_dir, "events", "event_id", "event_type", "user_id")
    events.write.json(f"{path}/json")
    table(spark, sf_dir, "region").write.orc(f"{path}/orc")
    a = read_with_schema(spark, f"{path}/csv", "csv", TABLES["nation"], header="true").select(F.lit("csv").alias("fmt"), F.col("n_nationkey").cast("long").alias("id"), F.col("n_name").alias("text"))
    b = read_with_schema(spark, f"{path}/json", "json", events.schema).select(F.lit("json"), "event_id", F.concat_ws(":", "event_type", F.col("user_id").cast("string")))
    c = read_with_schema(spark, f"{path}/orc", "orc", TABLES["region"]).select(F.lit("orc"), F.col("r_regionkey").cast("long"), "r_name")
    return a.union(b).union(c)


@query("run_log_roundtrip", f"WITH {trace_sql()} SELECT 'run' || (iteration % 3) AS run_id, count(*)::BIGINT AS n FROM t GROUP BY 1")
def _(spark, sf_dir):
    path = sinks.scratch_path(spark, "log")
    rows = trace(spark, sf_dir).withColumn("run_id", F.concat(F.lit("run"), F.col("iteration") % 3))
    sinks.write_run_log(rows, path)
    sinks.write_run_log(rows.where("run_id = 'run1'"), path)  # replaces that run alone
    return sinks.read_run_log(spark, path).groupBy("run_id").agg(F.count("*").alias("n"))


# ---- projections and filters -----------------------------------------------------------------------------------

@query("proj_net_target", "SELECT l_orderkey, l_linenumber, round(l_extendedprice * (1 - l_discount) * (1 + l_tax), 8) AS net, round((l_extendedprice - 50000) / 25000, 8) AS price_z, l_quantity::INTEGER AS quantity FROM lineitem")
def _(spark, sf_dir):
    li = table(spark, sf_dir, "lineitem")
    return li.select("l_orderkey", "l_linenumber", (F.col("l_extendedprice") * (1 - F.col("l_discount")) * (1 + F.col("l_tax"))).alias("net"), ((F.col("l_extendedprice") - 50000) / 25000).alias("price_z"), F.col("l_quantity").cast("int").alias("quantity"))


@query("filter_split", "SELECT doc_id, lang FROM documents WHERE ('0x' || substr(md5(doc_id::VARCHAR), 1, 8))::BIGINT / 4294967296.0 >= 0.85")
def _(spark, sf_dir):
    return table(spark, sf_dir, "documents", "doc_id", "lang").where(split_name(F.col("doc_id")) == "test")


@query("filter_compound", "SELECT p_partkey, p_brand, p_size FROM part WHERE p_size BETWEEN 5 AND 30 AND (p_brand IN (SELECT DISTINCT p_brand FROM part WHERE p_size = 7) OR p_type LIKE '%A%') AND regexp_matches(p_name, '[aeiou]') AND p_retailprice IS DISTINCT FROM NULL")
def _(spark, sf_dir):
    part = table(spark, sf_dir, "part")
    brands = part.where("p_size = 7").select(F.col("p_brand").alias("b")).distinct()
    hit = part.join(F.broadcast(brands), F.col("p_brand") == F.col("b"), "left")
    return hit.where(F.col("p_size").between(5, 30) & (F.col("b").isNotNull() | F.col("p_type").like("%A%")) & F.col("p_name").rlike("[aeiou]") & ~F.col("p_retailprice").eqNullSafe(F.lit(None))).select("p_partkey", "p_brand", "p_size")


# ---- joins -----------------------------------------------------------------------------------------------------

@query("join_inner_hash", "SELECT doc_id, lang, quality, toxic FROM documents JOIN labels USING (doc_id)")
def _(spark, sf_dir):
    return table(spark, sf_dir, "documents", "doc_id", "lang").join(table(spark, sf_dir, "labels"), "doc_id").select("doc_id", "lang", "quality", "toxic")


@query("join_broadcast", "SELECT c_custkey, n_name, r_name FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey")
def _(spark, sf_dir):
    nation, region = table(spark, sf_dir, "nation"), table(spark, sf_dir, "region")  # 25 and 5 rows by definition
    c = table(spark, sf_dir, "customer", "c_custkey", "c_nationkey")
    return c.join(F.broadcast(nation), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(region), F.col("n_regionkey") == F.col("r_regionkey")).select("c_custkey", "n_name", "r_name")


@query("join_sort_merge", "SELECT o_orderpriority, count(*)::BIGINT AS n, round(sum(l_quantity), 4) AS quantity FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1", 4)
def _(spark, sf_dir):
    o, li = table(spark, sf_dir, "orders", "o_orderkey", "o_orderpriority"), table(spark, sf_dir, "lineitem", "l_orderkey", "l_quantity")
    return o.hint("merge").join(li, F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderpriority").agg(F.count("*").alias("n"), F.sum("l_quantity").alias("quantity"))


@query("join_shuffle_hash", "SELECT p_brand, count(*)::BIGINT AS n, round(avg(l_discount), 8) AS discount FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1")
def _(spark, sf_dir):
    li, p = table(spark, sf_dir, "lineitem", "l_partkey", "l_discount"), table(spark, sf_dir, "part", "p_partkey", "p_brand")
    return li.join(p.hint("shuffle_hash"), F.col("l_partkey") == F.col("p_partkey")).groupBy("p_brand").agg(F.count("*").alias("n"), F.avg("l_discount").alias("discount"))


@query("join_left_outer", "SELECT d.doc_id, quality FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id")
def _(spark, sf_dir):
    return table(spark, sf_dir, "documents", "doc_id").join(table(spark, sf_dir, "labels"), "doc_id", "left").select("doc_id", "quality")


@query("join_right_outer", "SELECT s_suppkey, count(l_orderkey)::BIGINT AS n FROM (SELECT * FROM lineitem WHERE l_quantity > 49) RIGHT JOIN supplier ON l_suppkey = s_suppkey GROUP BY 1")
def _(spark, sf_dir):
    li = table(spark, sf_dir, "lineitem", "l_suppkey", "l_orderkey", "l_quantity").where("l_quantity > 49")
    return li.join(table(spark, sf_dir, "supplier", "s_suppkey"), F.col("l_suppkey") == F.col("s_suppkey"), "right").groupBy("s_suppkey").agg(F.count("l_orderkey").alias("n"))


@query("join_full_outer", "SELECT coalesce(a.k, b.k) AS k, a.n AS n_customers, b.n AS n_suppliers FROM (SELECT c_nationkey AS k, count(*)::BIGINT AS n FROM customer WHERE c_nationkey < 15 GROUP BY 1) a FULL JOIN (SELECT s_nationkey AS k, count(*)::BIGINT AS n FROM supplier WHERE s_nationkey > 8 GROUP BY 1) b ON a.k = b.k")
def _(spark, sf_dir):
    a = table(spark, sf_dir, "customer", "c_nationkey").where("c_nationkey < 15").groupBy(F.col("c_nationkey").alias("k")).agg(F.count("*").alias("n_customers"))
    b = table(spark, sf_dir, "supplier", "s_nationkey").where("s_nationkey > 8").groupBy(F.col("s_nationkey").alias("k")).agg(F.count("*").alias("n_suppliers"))
    return a.join(b, "k", "full")


_BATCH = "(event_id // 50)::INTEGER AS iteration, (event_id % 50 + 50)::INTEGER AS worker"


def _batch(spark, sf_dir):
    return table(spark, sf_dir, "events", "event_id", "user_id").select("event_id", "user_id", F.expr("CAST(event_id DIV 50 AS INT)").alias("iteration"), F.expr("CAST(event_id % 50 + 50 AS INT)").alias("worker"))


@query("join_semi_quorum", f"WITH {trace_sql()} SELECT event_id, b.iteration, b.worker FROM (SELECT event_id, {_BATCH} FROM events) b SEMI JOIN (SELECT * FROM tk WHERE k <= 94) w ON b.iteration = w.iteration AND b.worker = w.worker")
def _(spark, sf_dir):
    return _batch(spark, sf_dir).join(tr.winners(trace(spark, sf_dir), 94), ["iteration", "worker"], "left_semi").select("event_id", "iteration", "worker")


@query("join_anti_dropped", f"WITH {trace_sql()} SELECT event_id, b.iteration, b.worker FROM (SELECT event_id, {_BATCH} FROM events) b ANTI JOIN (SELECT * FROM tk WHERE k <= 94) w ON b.iteration = w.iteration AND b.worker = w.worker")
def _(spark, sf_dir):
    return _batch(spark, sf_dir).join(tr.winners(trace(spark, sf_dir), 94), ["iteration", "worker"], "left_anti").select("event_id", "iteration", "worker")


@query("join_cross_grid", "SELECT n::INTEGER AS n, g::INTEGER AS rate_step, m AS metric, seen FROM (VALUES (50), (70), (80), (90), (100)) a(n), range(4) b(g), (SELECT event_type AS m, count(*)::BIGINT AS seen FROM events WHERE value >= 0 GROUP BY 1) c")
def _(spark, sf_dir):
    """Every quorum with every rate and every kind of event."""
    n = spark.createDataFrame([(x,) for x in (50, 70, 80, 90, 100)], "n int")
    kinds = table(spark, sf_dir, "events", "event_type", "value").where("value >= 0").groupBy(F.col("event_type").alias("metric")).agg(F.count("*").alias("seen"))
    return n.crossJoin(spark.range(4).select(F.col("id").cast("int").alias("rate_step"))).crossJoin(kinds)


@query("join_theta_cdf", "SELECT g::DOUBLE AS t, count(*)::BIGINT AS n FROM events JOIN (SELECT unnest([10, 25, 50, 100, 200, 400]) AS g) ON value <= g GROUP BY 1")
def _(spark, sf_dir):
    grid = spark.createDataFrame([(float(x),) for x in (10, 25, 50, 100, 200, 400)], "t double")
    return table(spark, sf_dir, "events", "value").join(F.broadcast(grid), F.col("value") <= F.col("t")).groupBy("t").agg(F.count("*").alias("n"))


@query("join_range_knots", "WITH k AS (SELECT n AS lo, lead(n) OVER (ORDER BY n) AS hi FROM (VALUES (50), (70), (80), (90), (101)) v(n)), r AS (SELECT event_id, (50 + event_id % 51)::INTEGER AS n FROM events) SELECT event_id, n, lo, hi FROM r JOIN k ON n >= lo AND n < hi")
def _(spark, sf_dir):
    """The knots on both sides of each event's quorum."""
    knots = spark.createDataFrame([(50, 70), (70, 80), (80, 90), (90, 101)], "lo int, hi int")
    rows = table(spark, sf_dir, "events", "event_id").select("event_id", (F.col("event_id") % 51 + 50).cast("int").alias("n"))
    return rows.join(F.broadcast(knots), (F.col("n") >= F.col("lo")) & (F.col("n") < F.col("hi")))


@query("join_interval_events", "SELECT a.event_id AS first_id, b.event_id AS next_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def _(spark, sf_dir):
    """Pairs within an hour.  Rows meet in the hour bucket and the one after, so a busy user does not pair with a month."""
    e = table(spark, sf_dir, "events", "event_id", "user_id", "ts").withColumn("hour", F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / 3_600_000_000))
    a = e.select(F.col("event_id").alias("first_id"), "user_id", F.col("ts").alias("t0"), F.explode(F.array("hour", F.col("hour") + 1)).alias("hour"))
    b = e.select(F.col("event_id").alias("next_id"), "user_id", F.col("ts").alias("t1"), "hour")
    return a.join(b, ["user_id", "hour"]).where((F.col("t1") > F.col("t0")) & (F.col("t1") <= F.col("t0") + F.expr("INTERVAL 1 HOUR"))).select("first_id", "next_id")


@query("join_asof_version", """WITH a AS (SELECT user_id, ts, row_number() OVER (PARTITION BY user_id ORDER BY ts) AS v FROM events WHERE event_type = (SELECT min(event_type) FROM events)),
m AS (SELECT user_id, ts, max(v) AS v FROM a GROUP BY ALL) SELECT r.event_id, coalesce(m.v, 0)::BIGINT AS version FROM events r ASOF LEFT JOIN m ON r.user_id = m.user_id AND r.ts >= m.ts""")
def _(spark, sf_dir):
    """Updates (the first event type) of a user seen at each event."""
    e = table(spark, sf_dir, "events", "event_id", "user_id", "ts", "event_type")
    first = e.agg(F.min("event_type").alias("kind"))
    run = W.partitionBy("user_id").orderBy("ts").rangeBetween(W.unboundedPreceding, W.currentRow)
    rows = e.crossJoin(F.broadcast(first)).withColumn("_u", (F.col("event_type") == F.col("kind")).cast("long"))
    return rows.select("event_id", F.sum("_u").over(run).alias("version"))


@query("join_null_safe", "SELECT a.event_id, b.w FROM (SELECT event_id, nullif((props->>'k')::INTEGER % 4, 0) AS k FROM events) a JOIN (VALUES (1, 'one'), (2, 'two'), (NULL, 'none')) b(k, w) ON a.k IS NOT DISTINCT FROM b.k")
def _(spark, sf_dir):
    e = table(spark, sf_dir, "events", "event_id", "props").select("event_id", F.nullif(F.from_json("props", PROPS)["k"] % 4, F.lit(0)).alias("k"))
    names = spark.createDataFrame([(1, "one"), (2, "two"), (None, "none")], "k2 int, w string")
    return e.join(F.broadcast(names), F.col("k").eqNullSafe(F.col("k2"))).select("event_id", "w")


@query("join_self_runs", f"WITH {trace_sql()}, r AS (SELECT iteration, max(arrival) FILTER (k <= 94) AS a, max(arrival) AS b FROM tk GROUP BY 1) SELECT iteration, round(b - a, 8) AS gap, round(b / a, 8) AS ratio FROM r")
def _(spark, sf_dir):
    t = trace(spark, sf_dir)
    a, b = tr.sync_steps(t, 94).alias("a"), tr.sync_steps(t, 100).alias("b")
    return a.join(b, F.col("a.iteration") == F.col("b.iteration")).select("a.iteration", (F.col("b.step_time") - F.col("a.step_time")).alias("gap"), (F.col("b.step_time") / F.col("a.step_time")).alias("ratio"))


@query("join_lateral_explode", "SELECT vec_id, (i - 1)::INTEGER AS coord, round(embedding[i]::DOUBLE, 8) AS value FROM embeddings, range(1, 65) r(i)")
def _(spark, sf_dir):
    return table(spark, sf_dir, "embeddings", "vec_id", "embedding").select("vec_id", F.posexplode("embedding").alias("coord", "v")).select("vec_id", "coord", F.col("v").cast("double").alias("value"))


# ---- subqueries ------------------------------------------------------------------------------------------------

def _view(spark, sf_dir, *names):
    for n in names:
        table(spark, sf_dir, n).createOrReplaceTempView(f"qg_{n}")


@query("subq_exists", "SELECT c_custkey FROM customer c WHERE EXISTS (SELECT 1 FROM orders o WHERE o.o_custkey = c.c_custkey AND o.o_totalprice > 300000)")
def _(spark, sf_dir):
    _view(spark, sf_dir, "customer", "orders")
    return spark.sql("SELECT c_custkey FROM qg_customer c WHERE EXISTS (SELECT 1 FROM qg_orders o WHERE o.o_custkey = c.c_custkey AND o.o_totalprice > 300000)")


@query("subq_in", "SELECT doc_id, source FROM documents WHERE doc_id IN (SELECT doc_id FROM labels WHERE quality = 1)")
def _(spark, sf_dir):
    _view(spark, sf_dir, "documents", "labels")
    return spark.sql("SELECT doc_id, source FROM qg_documents WHERE doc_id IN (SELECT doc_id FROM qg_labels WHERE quality = 1)")


@query("subq_scalar", "SELECT event_id, round(value, 8) AS value FROM events WHERE value > 3 * (SELECT avg(value) FROM events)")
def _(spark, sf_dir):
    _view(spark, sf_dir, "events")
    return spark.sql("SELECT event_id, value FROM qg_events WHERE value > 3 * (SELECT avg(value) FROM qg_events)")


# ---- aggregates ------------------------------------------------------------------------------------------------

@query("agg_hash_partial_final", f"WITH {trace_sql()}, w AS (SELECT iteration, worker % 10 AS grp, avg(arrival) AS m FROM t GROUP BY ALL) SELECT iteration, round(avg(m), 8) AS mean_of_means FROM w GROUP BY 1")
def _(spark, sf_dir):
    return trace(spark, sf_dir).groupBy("iteration", (F.col("worker") % 10).alias("grp")).agg(F.avg("arrival").alias("m")).groupBy("iteration").agg(F.avg("m").alias("mean_of_means"))


@query("agg_distinct", "SELECT event_type, count(DISTINCT user_id)::BIGINT AS users FROM events GROUP BY 1")
def _(spark, sf_dir):
    return table(spark, sf_dir, "events", "event_type", "user_id").groupBy("event_type").agg(F.countDistinct("user_id").alias("users"))


def _grouped(kind: str) -> str:
    return f"SELECT (user_id % 3)::INTEGER AS grp, event_type, grouping_id((user_id % 3)::INTEGER, event_type)::BIGINT AS gid, count(*)::BIGINT AS n, round(avg(value), 8) AS mean FROM events GROUP BY {kind}"


def _groups(spark, sf_dir):
    return table(spark, sf_dir, "events", "user_id", "event_type", "value").withColumn("grp", (F.col("user_id") % 3).cast("int"))


def _measures():
    return [F.grouping_id().cast("long").alias("gid"), F.count("*").alias("n"), F.avg("value").alias("mean")]


@query("agg_grouping_sets", _grouped("GROUPING SETS (((user_id % 3)::INTEGER, event_type), ((user_id % 3)::INTEGER), ())"))
def _(spark, sf_dir):
    return _groups(spark, sf_dir).groupingSets([["grp", "event_type"], ["grp"], []], "grp", "event_type").agg(*_measures())


@query("agg_cube", _grouped("CUBE ((user_id % 3)::INTEGER, event_type)"))
def _(spark, sf_dir):
    return _groups(spark, sf_dir).cube("grp", "event_type").agg(*_measures())


@query("agg_rollup", _grouped("ROLLUP ((user_id % 3)::INTEGER, event_type)"))
def _(spark, sf_dir):
    return _groups(spark, sf_dir).rollup("grp", "event_type").agg(*_measures())


@query("agg_percentiles", f"WITH {trace_sql()} SELECT (worker % 4)::INTEGER AS grp, round(median(arrival), 8) AS p50, round(quantile_cont(arrival, 0.9), 8) AS p90, round(quantile_cont(arrival, 0.98), 8) AS p98 FROM t GROUP BY 1")
def _(spark, sf_dir):
    p = [F.expr(f"percentile_cont({q}) WITHIN GROUP (ORDER BY arrival)").alias(n) for q, n in ((0.5, "p50"), (0.9, "p90"), (0.98, "p98"))]
    return trace(spark, sf_dir).groupBy((F.col("worker") % 4).cast("int").alias("grp")).agg(*p)


@query("agg_percentile_sketch")
def _(spark, sf_dir):
    rows = trace(spark, sf_dir).groupBy((F.col("worker") % 4).cast("int").alias("grp")).agg(F.expr("kll_sketch_agg_double(arrival)").alias("s"), F.percentile_approx("arrival", 0.5, 1000).alias("p50_approx"))
    return rows.select("grp", F.expr("kll_sketch_get_quantile_double(s, 0.5D)").alias("p50_kll"), "p50_approx")


@query("agg_approx_distinct")
def _(spark, sf_dir):
    e = table(spark, sf_dir, "events", "ts", "user_id").groupBy(F.to_date("ts").alias("day"))
    return e.agg(F.approx_count_distinct("user_id").alias("users"), F.expr("hll_sketch_estimate(hll_sketch_agg(user_id))").alias("users_sketch"))


@query("agg_moments", "SELECT count(*)::BIGINT AS n, round(min(l_tax), 4) AS lo, round(max(l_tax), 4) AS hi, round(avg(l_quantity), 4) AS mean, round(stddev_samp(l_quantity), 4) AS sd, round(var_pop(l_quantity), 4) AS var, round(corr(l_quantity, l_extendedprice), 4) AS r, round(covar_samp(l_discount, l_tax) * 1000, 4) AS cov_x1000, round(regr_slope(l_extendedprice, l_quantity), 4) AS slope FROM lineitem", 4)
def _(spark, sf_dir):
    return table(spark, sf_dir, "lineitem").agg(
        F.count("*").alias("n"), F.min("l_tax").alias("lo"), F.max("l_tax").alias("hi"), F.avg("l_quantity").alias("mean"), F.stddev_samp("l_quantity").alias("sd"), F.var_pop("l_quantity").alias("var"),
        F.corr("l_quantity", "l_extendedprice").alias("r"), (F.covar_samp("l_discount", "l_tax") * 1000).alias("cov_x1000"), F.regr_slope("l_extendedprice", "l_quantity").alias("slope"),
    )


@query("agg_argmax", f"WITH {trace_sql()} SELECT iteration, worker AS slowest, round(arrival, 8) AS arrival FROM tk WHERE k = 100")
def _(spark, sf_dir):
    return trace(spark, sf_dir).groupBy("iteration").agg(F.max_by("worker", F.struct("arrival", "worker")).alias("slowest"), F.max("arrival").alias("arrival"))


@query("agg_filter_clause", f"WITH {trace_sql()} SELECT iteration, count(*) FILTER (k <= 94)::BIGINT AS used, count(*) FILTER (k > 94)::BIGINT AS dropped FROM tk GROUP BY 1")
def _(spark, sf_dir):
    return tr.sync_schedule(trace(spark, sf_dir), 94).groupBy("iteration").agg(F.count_if(F.col("used")).alias("used"), F.count_if(~F.col("used")).alias("dropped"))


@query("agg_pivot", "SELECT event_type, count(*) FILTER (user_id % 3 = 0)::BIGINT AS g0, count(*) FILTER (user_id % 3 = 1)::BIGINT AS g1, count(*) FILTER (user_id % 3 = 2)::BIGINT AS g2 FROM events GROUP BY 1")
def _(spark, sf_dir):
    return _groups(spark, sf_dir).groupBy("event_type").pivot("grp", [0, 1, 2]).agg(F.count(F.lit(1))).select("event_type", *[F.coalesce(F.col(str(i)), F.lit(0)).alias(f"g{i}") for i in range(3)])


@query("agg_unpivot", "SELECT event_type, ('g' || (user_id % 3)) AS grp, count(*)::BIGINT AS n FROM events GROUP BY ALL")
def _(spark, sf_dir):
    wide = _groups(spark, sf_dir).groupBy("event_type").pivot("grp", [0, 1, 2]).agg(F.count(F.lit(1))).select("event_type", *[F.col(str(i)).alias(f"g{i}") for i in range(3)])
    return wide.unpivot("event_type", ["g0", "g1", "g2"], "grp", "n").where("n is not null")


@query("agg_collect_sorted", f"WITH {trace_sql()} SELECT iteration, string_agg(worker::VARCHAR, ',' ORDER BY k) AS winners FROM tk WHERE k <= 10 GROUP BY 1")
def _(spark, sf_dir):
    first = tr.kth_arrival(trace(spark, sf_dir)).where("k <= 10")
    ordered = F.transform(F.array_sort(F.collect_list(F.struct("k", "worker"))), lambda s: s["worker"].cast("string"))
    return first.groupBy("iteration").agg(F.array_join(ordered, ",").alias("winners"))


@query("agg_having", f"WITH {trace_sql()} SELECT worker, round(avg(CASE WHEN k > 94 THEN 1.0 ELSE 0.0 END), 8) AS late_share FROM tk GROUP BY 1 HAVING avg(CASE WHEN k > 94 THEN 1.0 ELSE 0.0 END) > 0.06")
def _(spark, sf_dir):
    late = tr.sync_schedule(trace(spark, sf_dir), 94).groupBy("worker").agg(F.avg((~F.col("used")).cast("double")).alias("late_share"))
    return late.where("late_share > 0.06")


@query("agg_vector_mean", "SELECT label, (i - 1)::INTEGER AS coord, round(avg(embedding[i]::DOUBLE), 8) AS mean FROM embeddings, range(1, 65) r(i) GROUP BY ALL")
def _(spark, sf_dir):
    """Coordinate-wise means as 64 plain aggregates: one row per label and task is shuffled, nothing is exploded before."""
    e = table(spark, sf_dir, "embeddings", "label", "embedding")
    means = e.groupBy("label").agg(F.array(*[F.avg(F.col("embedding")[i].cast("double")) for i in range(64)]).alias("m"))
    return means.select("label", F.posexplode("m").alias("coord", "mean"))


# ---- windows ---------------------------------------------------------------------------------------------------

@query("win_ranking", f"WITH {trace_sql()} SELECT iteration, worker, k::INTEGER AS rn, rank() OVER w::INTEGER AS rk, dense_rank() OVER w::INTEGER AS dr, ntile(4) OVER (PARTITION BY iteration ORDER BY arrival, worker)::INTEGER AS quarter, round(percent_rank() OVER w, 8) AS pr, round(cume_dist() OVER w, 8) AS cd FROM tk WINDOW w AS (PARTITION BY iteration ORDER BY arrival)".replace("OVER w::INTEGER", "OVER w"))
def _(spark, sf_dir):
    w = W.partitionBy("iteration").orderBy("arrival")
    rows = trace(spark, sf_dir)
    return rows.select("iteration", "worker", F.row_number().over(tr.in_order()).alias("rn"), F.rank().over(w).cast("long").alias("rk"), F.dense_rank().over(w).cast("long").alias("dr"), F.ntile(4).over(tr.in_order()).alias("quarter"), F.percent_rank().over(w).alias("pr"), F.cume_dist().over(w).alias("cd"))


@query("win_lag_lead", f"WITH {trace_sql()} SELECT iteration, k, round(arrival - lag(arrival) OVER w, 8) AS gap, round(lead(arrival) OVER w - arrival, 8) AS next_gap FROM tk WINDOW w AS (PARTITION BY iteration ORDER BY k)")
def _(spark, sf_dir):
    w = W.partitionBy("iteration").orderBy("k")
    return tr.kth_arrival(trace(spark, sf_dir)).select("iteration", "k", (F.col("arrival") - F.lag("arrival").over(w)).alias("gap"), (F.lead("arrival").over(w) - F.col("arrival")).alias("next_gap"))


@query("win_first_last_nth", f"WITH {trace_sql()} SELECT iteration, round(min(arrival), 8) AS first_s, round(max(arrival), 8) AS last_s, round(max(arrival) FILTER (k = 94), 8) AS nth_s FROM tk GROUP BY 1")
def _(spark, sf_dir):
    w = W.partitionBy("iteration").orderBy("arrival", "worker").rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
    rows = trace(spark, sf_dir).select("iteration", F.first("arrival").over(w).alias("first_s"), F.last("arrival").over(w).alias("last_s"), F.nth_value("arrival", 94).over(w).alias("nth_s"))
    return rows.distinct()


@query("win_running_sum", "SELECT event_id, user_id, round(sum(CAST(value AS DECIMAL(18, 6))) OVER (PARTITION BY user_id ORDER BY event_id)::DOUBLE, 8) AS clock FROM events")
def _(spark, sf_dir):
    w = W.partitionBy("user_id").orderBy("event_id")
    return table(spark, sf_dir, "events").select("event_id", "user_id", F.sum(F.col("value").cast("decimal(18,6)")).over(w).cast("double").alias("clock"))


@query("win_running_min", "SELECT event_id, round(min(value) OVER (PARTITION BY user_id ORDER BY event_id), 8) AS best FROM events")
def _(spark, sf_dir):
    w = W.partitionBy("user_id").orderBy("event_id").rowsBetween(W.unboundedPreceding, W.currentRow)
    return table(spark, sf_dir, "events").select("event_id", F.min("value").over(w).alias("best"))


@query("win_rows_moving", "SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY event_id ROWS 9 PRECEDING), 8) AS mean10 FROM events")
def _(spark, sf_dir):
    w = W.partitionBy("user_id").orderBy("event_id").rowsBetween(-9, 0)
    return table(spark, sf_dir, "events").select("event_id", F.avg("value").over(w).alias("mean10"))


@query("win_range_seconds", "SELECT event_id, count(*) OVER (PARTITION BY event_type ORDER BY epoch_us(ts) RANGE BETWEEN 3600000000 PRECEDING AND CURRENT ROW)::BIGINT AS n_hour FROM events")
def _(spark, sf_dir):
    e = table(spark, sf_dir, "events", "event_id", "event_type", "ts").withColumn("us", F.unix_micros(F.col("ts").cast("timestamp")))
    return e.select("event_id", F.count("*").over(W.partitionBy("event_type").orderBy("us").rangeBetween(-3_600_000_000, 0)).alias("n_hour"))


# ---- sorting and limits ----------------------------------------------------------------------------------------

@query("sort_global", "SELECT event_id, row_number() OVER (ORDER BY value DESC, event_id)::BIGINT AS place FROM events")
def _(spark, sf_dir):
    """Places in a global order by range partitions and counts, no single task."""
    from ..operators.ordering import numbered

    rows = numbered(table(spark, sf_dir, "events", "event_id", "value"), [F.desc("value"), F.col("event_id")], "place")
    return rows.select("event_id", (F.col("place") + 1).alias("place"))


@query("sort_within", "SELECT user_id, count(*)::BIGINT AS n, min(event_id) AS first_id FROM events GROUP BY 1")
def _(spark, sf_dir):
    rows = table(spark, sf_dir, "events", "user_id", "event_id").repartition("user_id").sortWithinPartitions("user_id", "event_id")
    return rows.groupBy("user_id").agg(F.count("*").alias("n"), F.min("event_id").alias("first_id"))


@query("limit_offset", "SELECT event_id, round(value, 8) AS value FROM events ORDER BY events.value DESC, event_id LIMIT 10 OFFSET 5")
def _(spark, sf_dir):
    return table(spark, sf_dir, "events", "event_id", "value").orderBy(F.desc("value"), "event_id").offset(5).limit(10)


@query("topk_global", f"WITH {trace_sql()} SELECT iteration, worker, round(arrival, 8) AS arrival FROM t ORDER BY t.arrival DESC, iteration, worker LIMIT 20")
def _(spark, sf_dir):
    return trace(spark, sf_dir).orderBy(F.desc("arrival"), "iteration", "worker").limit(20)


@query("topk_per_group", f"WITH {trace_sql()} SELECT iteration, worker, round(arrival, 8) AS arrival FROM t QUALIFY row_number() OVER (PARTITION BY iteration ORDER BY t.arrival DESC, worker) <= 3")
def _(spark, sf_dir):
    w = W.partitionBy("iteration").orderBy(F.desc("arrival"), "worker")
    return trace(spark, sf_dir).withColumn("n", F.row_number().over(w)).where("n <= 3").drop("n")


# ---- sets ------------------------------------------------------------------------------------------------------

_SPLIT = "CASE WHEN h < 0.7 THEN 'train' WHEN h < 0.85 THEN 'validation' ELSE 'test' END"
_DOCS = f"d AS (SELECT doc_id, lang, {_SPLIT} AS split FROM (SELECT *, ('0x' || substr(md5(doc_id::VARCHAR), 1, 8))::BIGINT / 4294967296.0 AS h FROM documents))"


def _split_docs(spark, sf_dir):
    return table(spark, sf_dir, "documents", "doc_id", "lang").withColumn("split", split_name(F.col("doc_id")))


@query("set_union_all", f"WITH {_DOCS} SELECT doc_id, split FROM d WHERE split = 'train' UNION ALL SELECT doc_id, split FROM d WHERE split <> 'test'")
def _(spark, sf_dir):
    d = _split_docs(spark, sf_dir).select("doc_id", "split")
    return d.where("split = 'train'").union(d.where("split <> 'test'"))


@query("set_union_distinct", f"WITH {_DOCS} SELECT lang, split FROM d WHERE split = 'train' UNION SELECT lang, split FROM d WHERE split <> 'test'")
def _(spark, sf_dir):
    d = _split_docs(spark, sf_dir).select("lang", "split")
    return d.where("split = 'train'").union(d.where("split <> 'test'")).distinct()


@query("set_union_by_name", f"WITH {_DOCS} SELECT doc_id, lang, split FROM d UNION ALL BY NAME SELECT split, doc_id, NULL AS lang FROM d WHERE split = 'test'")
def _(spark, sf_dir):
    d = _split_docs(spark, sf_dir)
    return d.unionByName(d.where("split = 'test'").select("split", "doc_id"), allowMissingColumns=True)


_USED = f"{trace_sql()}, a AS (SELECT worker FROM tk WHERE k <= 94 AND iteration % 2 = 0), b AS (SELECT worker FROM tk WHERE k > 94)"


def _used(spark, sf_dir):
    k = tr.kth_arrival(trace(spark, sf_dir))
    return k.where("k <= 94 AND iteration % 2 = 0").select("worker"), k.where("k > 94").select("worker")


for _name, _op, _f in (("intersect", "INTERSECT", "intersect"), ("intersect_all", "INTERSECT ALL", "intersectAll"), ("except", "EXCEPT", "subtract"), ("except_all", "EXCEPT ALL", "exceptAll")):

    @query(f"set_{_name}", f"WITH {_USED} SELECT worker FROM a {_op} SELECT worker FROM b")
    def _(spark, sf_dir, f=_f):
        a, b = _used(spark, sf_dir)
        return getattr(a, f)(b)


# ---- functions -------------------------------------------------------------------------------------------------

@query("fn_string", "SELECT doc_id, md5(text) AS digest, lower(substr(text, 1, 12)) AS head, length(text)::INTEGER AS n, translate(lang, 'den', 'DEN') AS lang2, regexp_replace(substr(text, 1, 40), '[^A-Za-z ]', '', 'g') AS plain, len(string_split(text, ' '))::INTEGER AS parts FROM documents")
def _(spark, sf_dir):
    return table(spark, sf_dir, "documents").select("doc_id", F.md5("text").alias("digest"), F.lower(F.substring("text", 1, 12)).alias("head"), F.length("text").alias("n"), F.translate("lang", "den", "DEN").alias("lang2"), F.regexp_replace(F.substring("text", 1, 40), "[^A-Za-z ]", "").alias("plain"), F.size(F.split("text", " ", -1)).alias("parts"))


@query("fn_date", "SELECT o_orderkey, date_trunc('month', o_orderdate)::DATE AS month, year(o_orderdate)::INTEGER AS y, dayofyear(o_orderdate)::INTEGER AS doy, date_diff('day', DATE '1992-01-01', o_orderdate::DATE)::INTEGER AS days, (o_orderdate::DATE + 30) AS due FROM orders".replace("(o_orderdate::DATE + 30)", "(o_orderdate::DATE + 30)::DATE"))
def _(spark, sf_dir):
    d = F.to_date("o_orderdate")
    return table(spark, sf_dir, "orders", "o_orderkey", "o_orderdate").select("o_orderkey", F.trunc(d, "month").alias("month"), F.year(d).alias("y"), F.dayofyear(d).alias("doy"), F.datediff(d, F.lit("1992-01-01").cast("date")).alias("days"), F.date_add(d, 30).alias("due"))


@query("fn_math", "SELECT event_id, round(exp(-value / 100), 8) AS e, round(ln(1 + value), 8) AS l, round(pow(value, 0.5), 8) AS p, round(sqrt(value), 8) AS s, greatest(user_id, 75) AS hi, least(user_id, 75) AS lo, ((user_id - 80) % 7 + 7) % 7 AS m, sign(value - 50)::INTEGER AS sg, round(0.94 * pow(0.9, event_id % 20), 8) AS rate FROM events")
def _(spark, sf_dir):
    v, u = F.col("value"), F.col("user_id")
    return table(spark, sf_dir, "events").select("event_id", F.exp(-v / 100).alias("e"), F.log(1 + v).alias("l"), F.pow(v, F.lit(0.5)).alias("p"), F.sqrt(v).alias("s"), F.greatest(u, F.lit(75).cast("long")).alias("hi"), F.least(u, F.lit(75).cast("long")).alias("lo"), F.pmod(u - 80, F.lit(7)).alias("m"), F.signum(v - 50).cast("int").alias("sg"), (0.94 * F.pow(F.lit(0.9), F.col("event_id") % 20)).alias("rate"))


@query("fn_array", "WITH e AS (SELECT vec_id, list_transform(embedding, lambda x: x::DOUBLE) AS v FROM embeddings) SELECT vec_id, round(list_sum(list_transform(range(1, 65), lambda i: v[i] * (((37 * (i - 1) + 11) % 19 - 9) / 9))), 8) AS dot, round(list_max(v), 8) AS top, round(list_sum(list_filter(v, lambda x: x > 0)), 8) AS positive, round(list_sum(v[1:8]), 8) AS head FROM e")
def _(spark, sf_dir):
    v = F.transform("embedding", lambda x: x.cast("double"))
    total = lambda a: F.aggregate(a, F.lit(0.0), lambda s, x: s + x)
    return table(spark, sf_dir, "embeddings", "vec_id", "embedding").select("vec_id", vectors.dot(v, vectors.planted(64)).alias("dot"), F.array_max(v).alias("top"), total(F.filter(v, lambda x: x > 0)).alias("positive"), total(F.slice(v, 1, 8)).alias("head"))


@query("fn_map", "SELECT lang, source, count(*)::BIGINT * 2 AS twice FROM documents GROUP BY ALL")
def _(spark, sf_dir):
    counts = table(spark, sf_dir, "documents", "lang", "source").groupBy("lang", "source").agg(F.count("*").alias("n"))
    maps = counts.groupBy("lang").agg(F.map_from_entries(F.collect_list(F.struct("source", "n"))).alias("m"))
    summed = maps.select("lang", F.map_zip_with("m", F.transform_values("m", lambda k, v: v), lambda k, a, b: a + b).alias("m"))
    return summed.select("lang", F.explode("m").alias("source", "twice"))


@query("fn_json", "SELECT event_id, (props->>'k')::INTEGER AS k, (props->>'k') AS k_text FROM events")
def _(spark, sf_dir):
    p = F.from_json("props", PROPS)
    return table(spark, sf_dir, "events", "event_id", "props").select("event_id", p["k"].alias("k"), F.get_json_object(F.to_json(p), "$.k").alias("k_text"))


@query("fn_struct", "SELECT c_custkey, c_acctbal::BIGINT AS whole, c_mktsegment || '/' || c_nationkey AS label FROM (SELECT c_custkey, floor(c_acctbal) AS c_acctbal, c_mktsegment, c_nationkey FROM customer)")
def _(spark, sf_dir):
    s = table(spark, sf_dir, "customer").select("c_custkey", F.struct(F.floor("c_acctbal").alias("whole"), F.struct("c_mktsegment", "c_nationkey").alias("of")).alias("s"))
    return s.select("c_custkey", "s.whole", F.concat_ws("/", "s.of.c_mktsegment", F.col("s.of.c_nationkey").cast("string")).alias("label"))


@query("fn_conditional", "SELECT event_id, CASE WHEN value < 10 THEN 'low' WHEN value < 100 THEN 'mid' ELSE 'high' END AS band, coalesce(nullif(event_type, 'click'), 'none') AS kind FROM events")
def _(spark, sf_dir):
    return table(spark, sf_dir, "events").select("event_id", F.when(F.col("value") < 10, "low").when(F.col("value") < 100, "mid").otherwise("high").alias("band"), F.coalesce(F.nullif(F.col("event_type"), F.lit("click")), F.lit("none")).alias("kind"))


@query("fn_cast_try", "SELECT event_id, TRY_CAST(event_type AS INTEGER) AS bad, round(value / nullif((event_id % 3)::DOUBLE, 0), 8) AS ratio FROM events")
def _(spark, sf_dir):
    return table(spark, sf_dir, "events").select("event_id", F.expr("try_cast(event_type AS INT)").alias("bad"), F.try_divide(F.col("value"), (F.col("event_id") % 3).cast("double")).alias("ratio"))


@query("ema_recursive", f"WITH RECURSIVE {trace_sql()}, s AS (SELECT iteration, max(arrival) AS x FROM t GROUP BY 1), r AS (SELECT 0 AS iteration, (SELECT x FROM s WHERE iteration = 0) AS ema UNION ALL SELECT r.iteration + 1, 0.9::DOUBLE * ema + {1 - 0.9!r}::DOUBLE * x FROM r JOIN s ON s.iteration = r.iteration + 1) SELECT iteration::INTEGER AS iteration, round(ema, 8) AS ema FROM r")
def _(spark, sf_dir):
    """A running average of step times: one row per iteration, folded over the sorted list of a run."""
    steps = tr.sync_steps(trace(spark, sf_dir), 100).select("iteration", "step_time")
    listed = steps.agg(F.array_sort(F.collect_list(F.struct("iteration", "step_time"))).alias("s"))
    start = F.array(F.struct(F.col("s")[0]["iteration"].alias("iteration"), F.col("s")[0]["step_time"].alias("ema")))
    step = lambda acc, x: F.concat(acc, F.array(F.struct(x["iteration"].alias("iteration"), (0.9 * F.element_at(acc, -1)["ema"] + (1 - 0.9) * x["step_time"]).alias("ema"))))
    folded = listed.select(F.aggregate(F.slice("s", 2, F.size("s") - 1), start, step).alias("e"))
    return folded.select(F.explode("e").alias("e")).select("e.iteration", "e.ema")


@query("decay_recursive", "WITH RECURSIVE r AS (SELECT 0 AS t, 4.5::DOUBLE AS rate UNION ALL SELECT t + 1, rate * 0.94::DOUBLE FROM r WHERE t < 99) SELECT event_id, t, round(rate, 8) AS rate FROM events JOIN r ON event_id % 100 = t")
def _(spark, sf_dir):
    """The decayed rate of each event's step, in runs of a hundred steps."""
    rates = spark.sql("WITH RECURSIVE r(t, rate) AS (SELECT 0, CAST(4.5 AS DOUBLE) UNION ALL SELECT t + 1, rate * CAST(0.94 AS DOUBLE) FROM r WHERE t < 99) SELECT t, rate FROM r")
    return table(spark, sf_dir, "events", "event_id").join(F.broadcast(rates), F.col("event_id") % 100 == F.col("t")).select("event_id", "t", "rate")


# ---- user-defined functions ------------------------------------------------------------------------------------

_PLANTED = "list_sum(list_transform(range(1, 65), lambda i: embedding[i]::DOUBLE * (((37 * (i - 1) + 11) % 19 - 9) / 9)))"


@query("udf_arrow_dot", f"SELECT vec_id, round({_PLANTED}, 8) AS dot FROM embeddings")
def _(spark, sf_dir):
    return table(spark, sf_dir, "embeddings").select("vec_id", vectors.planted_dot("embedding").alias("dot"))


@query("udf_pandas_scalar", "SELECT event_id, round(1 / (1 + exp(-(value - 50) / 25)), 8) AS p FROM events")
def _(spark, sf_dir):
    return table(spark, sf_dir, "events").select("event_id", vectors.sigmoid((F.col("value") - 50) / 25).alias("p"))


@query("udf_grouped_agg", "SELECT label, round(sqrt(sum(m * m)), 8) AS norm FROM (SELECT label, i, avg(embedding[i]::DOUBLE) AS m FROM embeddings, range(1, 65) r(i) GROUP BY ALL) GROUP BY label")
def _(spark, sf_dir):
    """Norm of the mean vector: partial sums per task first, so that a hot label does not meet in one task row by row."""
    counted = F.concat(F.transform("embedding", lambda x: x.cast("double")), F.array(F.lit(1.0)))  # the last coordinate counts rows
    part = table(spark, sf_dir, "embeddings").select("label", F.pmod(F.xxhash64("vec_id"), F.lit(16)).alias("salt"), counted.alias("v")).groupBy("label", "salt").agg(vectors.vector_sum("v").alias("v"))
    total = part.groupBy("label").agg(vectors.vector_sum("v").alias("v")).withColumn("n", F.element_at("v", -1))
    return total.select("label", (F.sqrt(F.aggregate("v", F.lit(0.0), lambda s, x: s + x * x) - F.col("n") * F.col("n")) / F.col("n")).alias("norm"))


@query("udf_apply_grouped", f"WITH {trace_sql()}, x AS (SELECT iteration, max(arrival) AS s FROM tk GROUP BY 1) SELECT 100::INTEGER AS quorum, iteration, round(sum(s) OVER (ORDER BY iteration), 8) AS clock FROM x")
def _(spark, sf_dir):
    """Busy stragglers with a full quorum are plain full synchronous steps."""
    from ..timing.busy import busy_schedule

    return busy_schedule(trace(spark, sf_dir), [100])


@query("udf_map_arrow", "SELECT round(sum(value), 4) AS total, count(*)::BIGINT AS n FROM events", 4)
def _(spark, sf_dir):
    return vectors.partial_total(table(spark, sf_dir, "events", "value"), "value").agg(F.sum("total").alias("total"), F.sum("n").alias("n"))


@query("udtf_replay", "WITH RECURSIVE r AS (SELECT s_suppkey, s_acctbal / 777 AS target, 0 AS step, 1.0::DOUBLE AS theta FROM supplier UNION ALL SELECT s_suppkey, target, step + 1, theta - 0.1::DOUBLE * (theta - target) FROM r WHERE step < 20) SELECT s_suppkey, step, round(theta, 8) AS theta FROM r")
def _(spark, sf_dir):
    """Descent towards each supplier's balance."""
    rows = table(spark, sf_dir, "supplier", "s_suppkey", "s_acctbal").withColumn("target", F.col("s_acctbal") / 777)
    return rows.lateralJoin(vectors.QuadraticReplay(F.lit(1.0), F.lit(0.1), F.col("target").outer(), F.lit(20))).select("s_suppkey", "step", "theta")


@query("udf_sql_registered", "SELECT event_id, round(1 / (1 + exp(-value / 100)), 8) AS p FROM events")
def _(spark, sf_dir):
    vectors.register(spark)
    _view(spark, sf_dir, "events")
    return spark.sql("SELECT event_id, qg_sigmoid(value / 100) AS p FROM qg_events")
