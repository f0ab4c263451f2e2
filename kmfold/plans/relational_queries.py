"""Relational, function and streaming queries that feed, tag, measure and serve the methods."""

from __future__ import annotations

import uuid

from pyspark.sql import Window as W
from pyspark.sql import functions as F

from kmfold.functions import sqlapi
from kmfold.functions.vectors import lattice
from kmfold.operators import summaries
from kmfold.sources import datasource, points
from kmfold.staging import scratch_path, stage
from kmfold.streaming import keyed, log, windows

Q: dict = {}
SQL: dict[str, str] = {}


def query(sql: str | None = None):
    def add(f):
        Q[f.__name__] = f
        if sql is not None:
            SQL[f.__name__] = sql
        return f

    return add


def t(spark, sf_dir, name):
    return points.table(spark, sf_dir, name)


def cents(c):
    return F.sum(F.round(F.col(c) * 100).cast("bigint"))


# --- sources and sinks -----------------------------------------------------------------


@query("SELECT n_nationkey, n_name, n_regionkey FROM nation")
def source_csv(spark, sf_dir):
    p = scratch_path(spark, "csv")
    t(spark, sf_dir, "nation").write.option("header", True).csv(p)
    return spark.read.schema("n_nationkey int, n_name string, n_regionkey int").option("header", True).csv(p)


@query("SELECT event_id, event_type, value FROM events")
def source_json(spark, sf_dir):
    p = scratch_path(spark, "json")
    t(spark, sf_dir, "events").select("event_id", "event_type", "value").write.json(p)
    return spark.read.schema("event_id bigint, event_type string, value double").json(p)


@query("SELECT s_suppkey, s_name, s_nationkey FROM supplier")
def source_orc(spark, sf_dir):
    p = scratch_path(spark, "orc")
    t(spark, sf_dir, "supplier").select("s_suppkey", "s_name", "s_nationkey").write.orc(p)
    return spark.read.orc(p)


@query("SELECT r_name AS value FROM region")
def source_text(spark, sf_dir):
    p = scratch_path(spark, "text")
    t(spark, sf_dir, "region").select(F.col("r_name").alias("value")).write.text(p)
    return spark.read.text(p)


@query("SELECT o_orderstatus, count(*) AS n, min(o_orderkey) AS low FROM orders WHERE o_orderstatus = 'F' GROUP BY 1")
def sink_partitioned(spark, sf_dir):
    """Directories by a key; a filter on it reads its own only."""
    back = stage(t(spark, sf_dir, "orders").select("o_orderkey", "o_orderstatus"), "by_status", ["o_orderstatus"])
    return back.filter("o_orderstatus = 'F'").groupBy("o_orderstatus").agg(F.count("*").alias("n"), F.min("o_orderkey").alias("low"))


@query("SELECT count(*) AS n, CAST(sum(n_regionkey) AS BIGINT) AS s FROM nation")
def generated_source(spark, sf_dir):
    """A generated table of as many rows as nations."""
    n = t(spark, sf_dir, "nation").count()
    return spark.range(n).select(F.col("id"), (F.col("id") % 5).alias("r")).agg(F.count("*").alias("n"), F.sum("r").alias("s"))


@query(f"""WITH g AS (SELECT i.range AS id, j.range AS j, CAST(round((((list_reduce([CAST(i.range * 16 + j.range AS BIGINT) + 1, 40503, 69069, 1013904223], lambda h, c: (h * h + c * h + 3) % 2147483647) / 2147483647.0) * 2.0 - 1.0) * 10.0) * 1000) AS BIGINT) AS v FROM range(2000) i CROSS JOIN range(16) j),
e AS (SELECT vec_id, j.range AS j, CAST(round(CAST(embedding[j.range + 1] AS DOUBLE) * 1000) AS BIGINT) AS v FROM embeddings CROSS JOIN range(16) j)
SELECT CAST(sum((e.v + g.v) * (e.v + g.v)) AS BIGINT) AS cost, count(DISTINCT e.vec_id) AS n FROM e JOIN g ON e.vec_id % 2000 = g.id AND e.j = g.j""")
def generator_data_source(spark, sf_dir):
    """A generator behind the data source interface moves every embedding by one of its rows: these do not depend on its partitions."""
    datasource.register(spark)
    moves = spark.read.format("kmfold_cube").options(n=2000, d=16, partitions=3).load().select(F.col("id").alias("move"), lattice("x").alias("m"))
    pts = points.emb64(spark, sf_dir).select("id", F.slice(lattice("x"), 1, 16).alias("x"), F.pmod("id", F.lit(2000)).alias("move"))
    moved = pts.join(F.broadcast(moves), "move").select("id", F.zip_with("x", "m", lambda a, b: a + b).alias("x"))
    sq = F.aggregate("x", F.lit(0).cast("bigint"), lambda a, v: a + v * v)
    return moved.agg(F.sum(sq).alias("cost"), F.countDistinct("id").alias("n"))


@query("SELECT c_mktsegment, count(*) AS n, true AS no_exchange FROM customer JOIN orders ON c_custkey = o_custkey GROUP BY 1")
def sink_bucketed(spark, sf_dir):
    """Two tables bucketed by the join key: the join moves no row."""
    names = [f"kmfold_{uuid.uuid4().hex}" for _ in range(2)]
    frames = (t(spark, sf_dir, "customer").select("c_custkey", "c_mktsegment"), t(spark, sf_dir, "orders").select("o_custkey", "o_orderkey"))
    for df, name, key in zip(frames, names, ("c_custkey", "o_custkey")):
        df.write.bucketBy(4, key).sortBy(key).option("path", scratch_path(spark, name)).saveAsTable(name)
    joined = spark.table(names[0]).hint("merge").join(spark.table(names[1]), F.col("c_custkey") == F.col("o_custkey"))
    none = "Exchange" not in joined._jdf.queryExecution().executedPlan().toString()
    return joined.groupBy("c_mktsegment").agg(F.count("*").alias("n")).withColumn("no_exchange", F.lit(none))


# --- projection, filter -------------------------------------------------------------------


@query("SELECT l_orderkey, l_linenumber, l_quantity, l_extendedprice FROM lineitem WHERE l_quantity BETWEEN 10 AND 12 AND l_returnflag IN ('A', 'R') AND l_discount >= 0.05")
def filter_range_in(spark, sf_dir):
    return t(spark, sf_dir, "lineitem").filter(F.col("l_quantity").between(10, 12) & F.col("l_returnflag").isin("A", "R") & (F.col("l_discount") >= 0.05)).select("l_orderkey", "l_linenumber", "l_quantity", "l_extendedprice")


@query("SELECT p_partkey, p_name FROM part WHERE p_type LIKE '%E%' OR p_name LIKE 'a%' OR p_size IS NULL")
def filter_like_null(spark, sf_dir):
    return t(spark, sf_dir, "part").filter(F.col("p_type").like("%E%") | F.col("p_name").like("a%") | F.col("p_size").isNull()).select("p_partkey", "p_name")


@query("SELECT count(*) AS n FROM embeddings WHERE embedding IS NOT NULL AND len(embedding) = 64")
def filter_valid_vectors(spark, sf_dir):
    return points.points_from(t(spark, sf_dir, "embeddings"), "vec_id", "embedding", on_invalid="drop").filter(F.size("x") == 64).agg(F.count("*").alias("n"))


@query("SELECT vec_id AS id, generate_subscripts(embedding, 1) - 1 AS pos, CAST(round(CAST(unnest(embedding) AS DOUBLE) * 1000) AS BIGINT) AS v FROM embeddings")
def flatten_vectors(spark, sf_dir):
    flat = points.emb64(spark, sf_dir).select("id", F.posexplode("x").alias("pos", "v"))
    return flat.select("id", F.col("pos").cast("bigint").alias("pos"), F.round(F.col("v") * 1000).cast("bigint").alias("v"))


@query("SELECT count(*) AS n, true AS same FROM embeddings")
def rebuild_vectors(spark, sf_dir):
    e = points.emb64(spark, sf_dir)
    flat = e.select("id", F.posexplode("x").alias("pos", "v"))
    back = flat.groupBy("id").agg(F.transform(F.array_sort(F.collect_list(F.struct("pos", "v"))), lambda s: s["v"]).alias("y"))
    return e.join(back, "id").agg(F.count("*").alias("n"), F.every(F.col("x") == F.col("y")).alias("same"))


# --- joins ----------------------------------------------------------------------------------


@query("SELECT n_name, count(*) AS n, CAST(sum(CAST(round(c_acctbal * 100) AS BIGINT)) AS BIGINT) AS cents FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name")
def join_broadcast(spark, sf_dir):
    # 25 nations at every scale
    return t(spark, sf_dir, "customer").join(F.broadcast(t(spark, sf_dir, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count("*").alias("n"), cents("c_acctbal").alias("cents"))


@query("SELECT o_orderpriority, count(*) AS n, CAST(sum(CAST(round(l_extendedprice * 100) AS BIGINT)) AS BIGINT) AS cents FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1")
def join_sort_merge(spark, sf_dir):
    li = t(spark, sf_dir, "lineitem").select("l_orderkey", "l_extendedprice")
    return li.hint("merge").join(t(spark, sf_dir, "orders").select("o_orderkey", "o_orderpriority"), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderpriority").agg(F.count("*").alias("n"), cents("l_extendedprice").alias("cents"))


@query("SELECT c_mktsegment, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1")
def join_shuffle_hash(spark, sf_dir):
    c = t(spark, sf_dir, "customer").select("c_custkey", "c_mktsegment")
    return t(spark, sf_dir, "orders").select("o_custkey").join(c.hint("shuffle_hash"), F.col("o_custkey") == F.col("c_custkey")).groupBy("c_mktsegment").agg(F.count("*").alias("n"))


@query("SELECT a.r_name AS a, n.n_name AS b FROM region a JOIN nation n ON a.r_regionkey < n.n_regionkey")
def join_theta(spark, sf_dir):
    # five regions against 25 nations at every scale
    return t(spark, sf_dir, "region").join(F.broadcast(t(spark, sf_dir, "nation")), F.col("r_regionkey") < F.col("n_regionkey")).select(F.col("r_name").alias("a"), F.col("n_name").alias("b"))


@query("WITH w AS (SELECT range AS k, CAST('2024-01-01' AS TIMESTAMP) + to_hours(CAST(range * 36 AS INTEGER)) AS a, CAST('2024-01-01' AS TIMESTAMP) + to_hours(CAST(range * 36 + 48 AS INTEGER)) AS b FROM range(20)) SELECT k, count(*) AS n FROM events JOIN w ON ts >= a AND ts < b GROUP BY k")
def join_interval(spark, sf_dir):
    """Events in overlapping windows: bucketed to days so that equal keys meet, then the exact test."""
    start = F.expr("timestamp_ntz'2024-01-01 00:00:00' + make_dt_interval(0, cast(id * 36 as int))")
    w = spark.range(20).select(F.col("id").alias("k"), start.alias("a"), F.expr("timestamp_ntz'2024-01-01 00:00:00' + make_dt_interval(0, cast(id * 36 + 48 as int))").alias("b"))
    days = w.withColumn("d", F.explode(F.sequence(F.to_date("a"), F.to_date("b"))))
    e = t(spark, sf_dir, "events").select("ts").withColumn("d", F.to_date("ts"))
    return e.join(days, "d").filter("ts >= a AND ts < b").groupBy("k").agg(F.count("*").alias("n"))


@query("WITH v AS (SELECT event_id AS version, ts FROM events WHERE event_type = 'signup') SELECT e.event_id, coalesce(v.version, -1) AS version FROM events e ASOF LEFT JOIN v ON e.ts >= v.ts")
def join_asof(spark, sf_dir):
    """The last model version before each event: union by time, last non-null version inside a day, days carried over."""
    e = t(spark, sf_dir, "events").select("event_id", "ts", "event_type")
    at = e.filter("event_type = 'signup'").groupBy("ts").agg(F.max("event_id").alias("version"))
    both = e.select("ts", "event_id", F.lit(None).cast("bigint").alias("version"), F.lit(1).alias("o")).unionByName(at.select("ts", F.lit(None).cast("bigint").alias("event_id"), "version", F.lit(0).alias("o"))).withColumn("d", F.to_date("ts"))
    day_last = both.filter("version is not null").groupBy("d").agg(F.max_by("version", "ts").alias("v"))
    days = both.select("d").distinct().join(day_last, "d", "left")
    before = days.select("d", F.last("v", ignorenulls=True).over(W.orderBy("d").rowsBetween(W.unboundedPreceding, -1)).alias("carried"))  # one row a day
    inner = W.partitionBy("d").orderBy("ts", "o").rowsBetween(W.unboundedPreceding, W.currentRow)
    return both.join(before, "d").withColumn("seen", F.coalesce(F.last("version", ignorenulls=True).over(inner), "carried")).filter("o = 1").select("event_id", F.coalesce("seen", F.lit(-1).cast("bigint")).alias("version"))


@query("SELECT (SELECT count(*) FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders)) AS semi, (SELECT count(*) FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders)) AS anti, (SELECT count(*) FROM customer LEFT JOIN orders ON c_custkey = o_custkey) AS outer_rows, (SELECT count(*) FROM (SELECT DISTINCT s_nationkey FROM supplier) a FULL JOIN (SELECT DISTINCT c_nationkey FROM customer) b ON s_nationkey = c_nationkey) AS full_rows")
def join_semi_anti_outer(spark, sf_dir):
    c, o = t(spark, sf_dir, "customer").select("c_custkey", "c_nationkey"), t(spark, sf_dir, "orders").select(F.col("o_custkey").alias("c_custkey"))
    s = t(spark, sf_dir, "supplier").select("s_nationkey").distinct()
    parts = [c.join(o, "c_custkey", "left_semi").agg(F.count("*").alias("semi")), c.join(o, "c_custkey", "left_anti").agg(F.count("*").alias("anti")), c.join(o, "c_custkey", "left").agg(F.count("*").alias("outer_rows")), s.join(c.select("c_nationkey").distinct(), F.col("s_nationkey") == F.col("c_nationkey"), "full_outer").agg(F.count("*").alias("full_rows"))]
    out = parts[0]
    for p in parts[1:]:
        out = out.crossJoin(p)  # single rows
    return out


@query("SELECT a.n_name AS a, b.n_name AS b FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey")
def join_self(spark, sf_dir):
    n = t(spark, sf_dir, "nation")
    a, b = n.alias("a"), n.alias("b")
    return a.join(b, (F.col("a.n_regionkey") == F.col("b.n_regionkey")) & (F.col("a.n_nationkey") < F.col("b.n_nationkey"))).select(F.col("a.n_name").alias("a"), F.col("b.n_name").alias("b"))


@query("SELECT vec_id AS id, count(*) AS large FROM (SELECT vec_id, unnest(embedding) AS v FROM embeddings) WHERE v > 0.2 GROUP BY 1")
def join_lateral(spark, sf_dir):
    points.emb64(spark, sf_dir).createOrReplaceTempView("kmfold_pts")
    return spark.sql("SELECT id, count(*) AS large FROM kmfold_pts, LATERAL explode(x) AS e(v) WHERE v > 0.2 GROUP BY id")


# --- aggregates -----------------------------------------------------------------------------------


@query("SELECT l_returnflag, l_linestatus, count(*) AS n, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS qty, CAST(sum(CAST(round(l_extendedprice * 100) AS BIGINT)) AS BIGINT) AS cents FROM lineitem GROUP BY 1, 2")
def aggregate_hash(spark, sf_dir):
    return t(spark, sf_dir, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.sum(F.col("l_quantity").cast("bigint")).alias("qty"), cents("l_extendedprice").alias("cents"))


@query("SELECT event_type, count(DISTINCT user_id) AS users, true AS near FROM events GROUP BY 1")
def aggregate_distinct(spark, sf_dir):
    g = t(spark, sf_dir, "events").groupBy("event_type").agg(F.countDistinct("user_id").alias("users"), F.approx_count_distinct("user_id", 0.02).alias("a"))
    return g.select("event_type", "users", (F.abs(F.col("a") - F.col("users")) <= 0.1 * F.col("users")).alias("near"))


@query("SELECT count(DISTINCT user_id) AS users, true AS near FROM events")
def aggregate_sketch_union(spark, sf_dir):
    g = t(spark, sf_dir, "events").groupBy("event_type").agg(F.hll_sketch_agg("user_id").alias("s"), F.collect_set("user_id").alias("u"))
    return g.agg(F.size(F.array_distinct(F.flatten(F.collect_list("u")))).cast("bigint").alias("users"), F.hll_sketch_estimate(F.hll_union_agg("s")).alias("e")).select("users", (F.abs(F.col("e") - F.col("users")) <= 0.1 * F.col("users")).alias("near"))


@query("SELECT coalesce(l_returnflag, '*') AS flag, coalesce(l_linestatus, '*') AS status, count(*) AS n FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)")
def aggregate_rollup(spark, sf_dir):
    return t(spark, sf_dir, "lineitem").rollup("l_returnflag", "l_linestatus").agg(F.count("*").alias("n")).select(F.coalesce("l_returnflag", F.lit("*")).alias("flag"), F.coalesce("l_linestatus", F.lit("*")).alias("status"), "n")


@query("SELECT coalesce(l_returnflag, '*') AS flag, coalesce(l_linestatus, '*') AS status, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus))")
def aggregate_grouping_sets(spark, sf_dir):
    t(spark, sf_dir, "lineitem").createOrReplaceTempView("kmfold_lineitem")
    return spark.sql("SELECT coalesce(l_returnflag, '*') AS flag, coalesce(l_linestatus, '*') AS status, count(*) AS n FROM kmfold_lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus))")


@query("SELECT strftime(ts, '%Y-%m-%d') AS day, count(*) FILTER (event_type = 'click') AS click, count(*) FILTER (event_type = 'view') AS view FROM events GROUP BY 1")
def aggregate_pivot(spark, sf_dir):
    g = t(spark, sf_dir, "events").select(F.date_format("ts", "yyyy-MM-dd").alias("day"), "event_type", F.lit(1).alias("one")).groupBy("day").pivot("event_type", ["click", "view"]).agg(F.count("one"))
    return g.select("day", F.coalesce("click", F.lit(0)).alias("click"), F.coalesce("view", F.lit(0)).alias("view"))


@query("SELECT l_returnflag, m.measure, m.v FROM (SELECT l_returnflag, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS qty, count(*) AS n FROM lineitem GROUP BY 1) s, LATERAL (VALUES ('qty', s.qty), ('n', s.n)) m(measure, v)")
def aggregate_unpivot(spark, sf_dir):
    g = t(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(F.sum(F.col("l_quantity").cast("bigint")).alias("qty"), F.count("*").alias("n"))
    return g.unpivot("l_returnflag", ["qty", "n"], "measure", "v")


@query("SELECT l_returnflag, median(l_quantity) AS med, quantile_cont(l_quantity, 0.9) AS p90 FROM lineitem GROUP BY 1")
def aggregate_quantiles(spark, sf_dir):
    return t(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(F.median("l_quantity").alias("med"), F.percentile("l_quantity", 0.9).alias("p90"))


@query("SELECT l_linestatus, round(corr(l_quantity, l_extendedprice), 6) AS r, round(stddev_samp(l_quantity), 6) AS sd, round(covar_pop(l_discount, l_tax), 9) AS cov, count(*) FILTER (l_quantity > 25) AS many FROM lineitem GROUP BY 1")
def aggregate_moments(spark, sf_dir):
    return t(spark, sf_dir, "lineitem").groupBy("l_linestatus").agg(F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("r"), F.round(F.stddev_samp("l_quantity"), 6).alias("sd"), F.round(F.covar_pop("l_discount", "l_tax"), 9).alias("cov"), F.count_if(F.col("l_quantity") > 25).alias("many"))


@query("SELECT o_orderstatus, arg_min(o_orderkey, (o_totalprice, o_orderkey)) AS cheapest, arg_max(o_orderkey, (o_totalprice, o_orderkey)) AS dearest FROM orders GROUP BY 1")
def aggregate_min_by(spark, sf_dir):
    s = F.struct("o_totalprice", "o_orderkey")
    return t(spark, sf_dir, "orders").groupBy("o_orderstatus").agg(F.min_by("o_orderkey", s).alias("cheapest"), F.max_by("o_orderkey", s).alias("dearest"))


@query("SELECT l_linestatus, count(*) AS n, true AS sketch_near, true AS bins_add_up FROM lineitem GROUP BY 1")
def aggregate_sketches(spark, sf_dir):
    """Quantile sketch and histogram beside the exact median."""
    g = t(spark, sf_dir, "lineitem").groupBy("l_linestatus").agg(F.count("*").alias("n"), F.median("l_extendedprice").alias("m"), F.percentile_approx("l_extendedprice", 0.5, 10000).alias("a"), F.histogram_numeric("l_quantity", F.lit(10)).alias("h"))
    bins = F.aggregate("h", F.lit(0.0), lambda s, b: s + b["y"])
    return g.select("l_linestatus", "n", (F.abs(F.col("a") - F.col("m")) <= 0.02 * F.col("m")).alias("sketch_near"), (F.abs(bins - F.col("n")) < 0.5).alias("bins_add_up"))


@query("SELECT n_regionkey, string_agg(n_name, ',' ORDER BY n_name) AS names FROM nation GROUP BY 1")
def aggregate_listagg(spark, sf_dir):
    t(spark, sf_dir, "nation").createOrReplaceTempView("kmfold_nation")
    return spark.sql("SELECT n_regionkey, listagg(n_name, ',') WITHIN GROUP (ORDER BY n_name) AS names FROM kmfold_nation GROUP BY n_regionkey")


@query("SELECT event_type, true AS near FROM events GROUP BY 1")
def stratified_sample(spark, sf_dir):
    e = t(spark, sf_dir, "events").select("event_id", "event_type")
    kinds = {k: 0.3 for k in ("click", "error", "purchase", "signup", "view")}
    a, b = e.groupBy("event_type").agg(F.count("*").alias("n")), e.sampleBy("event_type", kinds, seed=5).groupBy("event_type").agg(F.count("*").alias("m"))
    return a.join(b, "event_type").select("event_type", (F.abs(F.col("m") / F.col("n") - 0.3) < 0.15).alias("near"))


@query("SELECT l_returnflag, count(*) AS n FROM lineitem WHERE l_quantity >= 40 GROUP BY 1")
def sql_parameters(spark, sf_dir):
    """Named parameters in SQL text."""
    t(spark, sf_dir, "lineitem").createOrReplaceTempView("kmfold_lineitem")
    return spark.sql("SELECT l_returnflag, count(*) AS n FROM kmfold_lineitem WHERE l_quantity >= :low GROUP BY l_returnflag", args={"low": 40})


# --- windows, order, sets ---------------------------------------------------------------------------


@query("SELECT o_custkey, o_orderkey, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, ntile(3) OVER w AS nt FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey)")
def window_ranking(spark, sf_dir):
    w = W.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return t(spark, sf_dir, "orders").select("o_custkey", "o_orderkey", F.row_number().over(w).cast("bigint").alias("rn"), F.rank().over(w).cast("bigint").alias("rk"), F.dense_rank().over(w).cast("bigint").alias("dr"), F.ntile(3).over(w).cast("bigint").alias("nt"))


@query("SELECT event_id, coalesce(event_id - lag(event_id) OVER w, -1) AS gap, first_value(event_id) OVER w AS first_id FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def window_analytic(spark, sf_dir):
    w = W.partitionBy("user_id").orderBy("ts", "event_id")
    e = t(spark, sf_dir, "events")
    return e.select("event_id", F.coalesce(F.col("event_id") - F.lag("event_id").over(w), F.lit(-1).cast("bigint")).alias("gap"), F.first("event_id").over(w).alias("first_id"))


@query("SELECT event_id, CAST(sum(CAST(round(value * 100) AS BIGINT)) OVER (PARTITION BY event_type ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS BIGINT) AS three FROM events")
def window_frame(spark, sf_dir):
    w = W.partitionBy("event_type").orderBy("ts", "event_id").rowsBetween(-2, 0)
    return t(spark, sf_dir, "events").select("event_id", F.sum(F.round(F.col("value") * 100).cast("bigint")).over(w).alias("three"))


@query("SELECT p_brand, p_partkey FROM (SELECT *, row_number() OVER (PARTITION BY p_brand ORDER BY p_retailprice DESC, p_partkey) AS r FROM part) WHERE r <= 3")
def top_of_group(spark, sf_dir):
    w = W.partitionBy("p_brand").orderBy(F.desc("p_retailprice"), "p_partkey")
    return t(spark, sf_dir, "part").withColumn("r", F.row_number().over(w)).filter("r <= 3").select("p_brand", "p_partkey")


@query("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20")
def top_rows(spark, sf_dir):
    return t(spark, sf_dir, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(20).select("o_orderkey", "o_totalprice")


@query("SELECT 'both' AS kind, count(*) AS n FROM (SELECT s_nationkey FROM supplier INTERSECT SELECT c_nationkey FROM customer) UNION ALL SELECT 'customer only', count(*) FROM (SELECT c_nationkey FROM customer EXCEPT SELECT s_nationkey FROM supplier) UNION ALL SELECT 'any', count(*) FROM (SELECT s_nationkey FROM supplier UNION SELECT c_nationkey FROM customer)")
def set_operations(spark, sf_dir):
    s, c = t(spark, sf_dir, "supplier").select(F.col("s_nationkey").alias("k")), t(spark, sf_dir, "customer").select(F.col("c_nationkey").alias("k"))
    row = lambda df, kind: df.agg(F.count("*").alias("n")).select(F.lit(kind).alias("kind"), "n")
    return row(s.intersect(c), "both").unionByName(row(c.subtract(s), "customer only")).unionByName(row(s.union(c).distinct(), "any"))


@query("SELECT 3 AS parts, count(*) AS w FROM embeddings")
def summary_union(spark, sf_dir):
    """Summaries of three shards, united and reduced."""
    e = points.emb64(spark, sf_dir)
    parts = [stage(summaries.direct_summary(e.filter(F.pmod("id", F.lit(3)) == i), 5, factor=10, seed=i).withColumn("node", F.lit(i).cast("bigint")), "part") for i in range(3)]
    one = summaries.reduce_summary(summaries.union_summaries(*parts), 5, factor=10)
    return one.agg(F.sum("w").alias("w")).select(F.lit(3).alias("parts"), "w")


# --- functions ------------------------------------------------------------------------------------------


@query("SELECT p_partkey, upper(p_name) AS up, length(p_type) AS n, concat_ws('-', p_brand, CAST(p_size AS VARCHAR)) AS tag, replace(p_name, 'a', '4') AS leet, levenshtein(p_brand, 'Brand#11') AS dist FROM part")
def string_functions(spark, sf_dir):
    return t(spark, sf_dir, "part").select("p_partkey", F.upper("p_name").alias("up"), F.length("p_type").cast("bigint").alias("n"), F.concat_ws("-", "p_brand", F.col("p_size").cast("string")).alias("tag"), F.translate("p_name", "a", "4").alias("leet"), F.levenshtein("p_brand", F.lit("Brand#11")).cast("bigint").alias("dist"))


@query("SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS first, date_diff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE)) AS days FROM orders")
def date_functions(spark, sf_dir):
    d = F.to_date("o_orderdate")
    return t(spark, sf_dir, "orders").select("o_orderkey", F.year("o_orderdate").cast("bigint").alias("y"), F.month("o_orderdate").cast("bigint").alias("m"), F.date_format(F.trunc(d, "month"), "yyyy-MM-dd").alias("first"), F.datediff(d, F.lit("1992-01-01").cast("date")).cast("bigint").alias("days"))


@query("SELECT event_id, round(sqrt(abs(value)), 6) AS s, floor(value) AS f, round(ln(abs(value) + 1), 6) AS l, greatest(value, 10.0) AS g, user_id % 7 AS m FROM events")
def math_functions(spark, sf_dir):
    v = F.col("value")
    return t(spark, sf_dir, "events").select("event_id", F.round(F.sqrt(F.abs(v)), 6).alias("s"), F.floor(v).cast("double").alias("f"), F.round(F.log(F.abs(v) + 1), 6).alias("l"), F.greatest(v, F.lit(10.0)).alias("g"), F.pmod("user_id", F.lit(7)).alias("m"))


@query("SELECT vec_id AS id, len(list_filter(embedding, lambda v: v > 0)) AS positive, CAST(list_position(embedding, list_max(embedding)) - 1 AS BIGINT) AS top, CAST(round(list_sum(embedding[1:8]) * 1000) AS BIGINT) AS eight FROM embeddings")
def array_functions(spark, sf_dir):
    e = t(spark, sf_dir, "embeddings")
    x = F.col("embedding")
    return e.select(F.col("vec_id").alias("id"), F.size(F.filter(x, lambda v: v > 0)).cast("bigint").alias("positive"), (F.array_position(x, F.array_max(x)) - 1).cast("bigint").alias("top"), F.round(F.aggregate(F.slice(x, 1, 8), F.lit(0.0), lambda s, v: s + v.cast("double")) * 1000).cast("bigint").alias("eight"))


@query("SELECT label, CAST(sum(n) AS BIGINT) AS n, CAST(max(n) AS BIGINT) AS top FROM (SELECT label, vec_id % 4 AS g, count(*) AS n FROM embeddings GROUP BY 1, 2) GROUP BY 1")
def map_functions(spark, sf_dir):
    c = t(spark, sf_dir, "embeddings").groupBy("label", F.pmod("vec_id", F.lit(4)).alias("g")).agg(F.count("*").alias("n"))
    m = c.groupBy("label").agg(F.map_from_entries(F.collect_list(F.struct("g", "n"))).alias("m"))
    return m.select("label", F.aggregate(F.map_values("m"), F.lit(0).cast("bigint"), lambda a, v: a + v).alias("n"), F.array_max(F.map_values("m")).alias("top"))


@query("SELECT event_id, CAST(json_extract_string(props, '$.k') AS INTEGER) AS k FROM events")
def json_functions(spark, sf_dir):
    return t(spark, sf_dir, "events").select("event_id", F.from_json("props", "k int")["k"].alias("k"))


@query("SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")
def variant_functions(spark, sf_dir):
    return t(spark, sf_dir, "events").select("event_id", F.try_variant_get(F.parse_json("props"), "$.k", "bigint").alias("k"))


@query("SELECT c_custkey, CASE WHEN c_acctbal < 0 THEN 'debt' WHEN c_acctbal < 5000 THEN 'mid' ELSE 'high' END AS band, coalesce(nullif(c_mktsegment, 'BUILDING'), 'none') AS seg, TRY_CAST(c_name AS INTEGER) IS NULL AS bad FROM customer")
def conditional_functions(spark, sf_dir):
    b = F.when(F.col("c_acctbal") < 0, "debt").when(F.col("c_acctbal") < 5000, "mid").otherwise("high")
    return t(spark, sf_dir, "customer").select("c_custkey", b.alias("band"), F.coalesce(F.nullif("c_mktsegment", F.lit("BUILDING")), F.lit("none")).alias("seg"), F.col("c_name").try_cast("int").isNull().alias("bad"))


@query("SELECT count(*) AS n FROM lineitem WHERE l_extendedprice > (SELECT avg(l_extendedprice) FROM lineitem) AND EXISTS (SELECT 1 FROM orders WHERE o_orderkey = l_orderkey AND o_orderstatus = 'O')")
def subqueries(spark, sf_dir):
    t(spark, sf_dir, "lineitem").createOrReplaceTempView("kmfold_lineitem")
    t(spark, sf_dir, "orders").createOrReplaceTempView("kmfold_orders")
    return spark.sql("SELECT count(*) AS n FROM kmfold_lineitem WHERE l_extendedprice > (SELECT avg(l_extendedprice) FROM kmfold_lineitem) AND EXISTS (SELECT 1 FROM kmfold_orders WHERE o_orderkey = l_orderkey AND o_orderstatus = 'O')")


@query("SELECT l_linenumber, count(*) AS n FROM lineitem WHERE l_orderkey % 10 = 3 GROUP BY 1")
def keyed_sample(spark, sf_dir):
    """A sample keyed by id, the same in every run."""
    return t(spark, sf_dir, "lineitem").filter(F.pmod("l_orderkey", F.lit(10)) == 3).groupBy("l_linenumber").agg(F.count("*").alias("n"))


@query("SELECT count(*) AS n, true AS within FROM lineitem")
def random_sample(spark, sf_dir):
    li = t(spark, sf_dir, "lineitem").select("l_orderkey")
    return li.agg(F.count("*").alias("n")).crossJoin(li.sample(0.1, seed=3).agg(F.count("*").alias("m"))).select("n", (F.abs(F.col("m") / F.col("n") - 0.1) < 0.02).alias("within"))


# --- SQL functions of the engine ----------------------------------------------------------------------------


@query("SELECT label, count(*) AS n, true AS equal FROM embeddings GROUP BY label")
def sql_aggregate(spark, sf_dir):
    """The vectorized aggregate agrees with the built-in way."""
    from kmfold.functions import features

    sqlapi.register(spark)
    e = points.emb64(spark, sf_dir)
    e.createOrReplaceTempView("kmfold_pts")
    a = spark.sql("SELECT label, set_cost(x, w) AS c FROM kmfold_pts GROUP BY label").join(e.groupBy("label").agg(F.count("*").alias("n")), "label")
    b = features.cf_agg(e, ["label"]).select("label", features.cf_within(F.col("cf")).alias("d"))
    return a.join(b, "label").select("label", "n", (F.abs(F.col("c") - F.col("d")) < 1e-6).alias("equal"))


@query("SELECT vec_id // 100 AS piece, count(*) AS n, true AS lower FROM embeddings GROUP BY 1")
def sql_projection(spark, sf_dir):
    """The projection as a table function over partitions of a table."""
    sqlapi.register(spark)
    e = points.emb64(spark, sf_dir).select("id", "x", "w", F.expr("id div 100").alias("piece"))
    e.createOrReplaceTempView("kmfold_pieces")
    out = spark.sql("SELECT id, x, w FROM rank_l_projection(8, TABLE(kmfold_pieces) PARTITION BY piece ORDER BY id)")
    sq = F.aggregate("x", F.lit(0.0), lambda s, v: s + v * v)
    a = out.groupBy(F.expr("id div 100").alias("piece")).agg(F.count("*").alias("n"), F.sum(sq).alias("a"))
    b = e.groupBy("piece").agg(F.sum(sq).alias("b"))
    return a.join(b, "piece").select("piece", "n", (F.col("a") <= F.col("b") + 1e-9).alias("lower"))


@query("SELECT count(*) AS w FROM embeddings")
def sql_summary(spark, sf_dir):
    sqlapi.register(spark)
    points.emb64(spark, sf_dir).select("id", "x", "w", F.pmod("id", F.lit(4)).alias("shard")).createOrReplaceTempView("kmfold_shards")
    return spark.sql("SELECT sum(w) AS w FROM sphere_summary(50, TABLE(kmfold_shards) PARTITION BY shard)")


# --- streaming ----------------------------------------------------------------------------------------------


@query("SELECT strftime(ts, '%Y-%m-%d') AS day, event_type, count(*) AS n, CAST(sum(CAST(round(value * 100) AS BIGINT)) AS BIGINT) AS cents FROM events GROUP BY 1, 2")
def stream_event_windows(spark, sf_dir):
    """Tumbling windows in complete mode: the last state is the batch answer."""
    out = windows.run_to_table(windows.tumbling(windows.replay(spark, sf_dir)), "complete")
    last = out.agg(F.max("_batch").alias("_batch"))
    return out.join(last, "_batch").select(F.date_format(F.col("w.start"), "yyyy-MM-dd").alias("day"), "event_type", "n", "cents")


@query("WITH d AS (SELECT CAST(date_trunc('day', ts) AS DATE) AS d FROM events), w AS (SELECT d AS start FROM d UNION ALL SELECT d - 1 FROM d) SELECT strftime(start, '%Y-%m-%d') AS start, count(*) AS n FROM w GROUP BY 1")
def stream_sliding_windows(spark, sf_dir):
    out = windows.run_to_table(windows.sliding(windows.replay(spark, sf_dir)), "complete")
    last = out.agg(F.max("_batch").alias("_batch"))
    return out.join(last, "_batch").select(F.date_format(F.col("w.start"), "yyyy-MM-dd").alias("start"), "n")


@query("WITH g AS (SELECT user_id, ts, CASE WHEN ts >= lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 6 HOUR OR lag(ts) OVER (PARTITION BY user_id ORDER BY ts) IS NULL THEN 1 ELSE 0 END AS s FROM events), k AS (SELECT user_id, ts, sum(s) OVER (PARTITION BY user_id ORDER BY ts) AS k FROM g) SELECT count(*) AS sessions, CAST(sum(n) AS BIGINT) AS events, max(n) AS longest FROM (SELECT user_id, k, count(*) AS n FROM k GROUP BY 1, 2)")
def stream_session(spark, sf_dir):
    out = windows.run_to_table(windows.sessions(windows.replay(spark, sf_dir)), "complete")
    last = out.agg(F.max("_batch").alias("_batch"))
    return out.join(last, "_batch").agg(F.count("*").alias("sessions"), F.sum("n").alias("events"), F.max("n").alias("longest"))


@query("SELECT count(*) AS n, count(DISTINCT event_id) AS ids FROM events")
def stream_dedup(spark, sf_dir):
    """The table twice in one stream: every event comes out once."""
    e = t(spark, sf_dir, "events")
    path = windows.split_files(e.unionByName(e), 4, "ts")
    out = windows.run_to_table(windows.first_of_each(windows.file_stream(spark, path, windows.EVENTS, 4), ["event_id"]), "append")
    return out.agg(F.count("*").alias("n"), F.countDistinct("event_id").alias("ids"))


@query("SELECT r_name, count(*) AS n FROM events JOIN nation ON user_id % 25 = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1")
def stream_static_join(spark, sf_dir):
    dim = t(spark, sf_dir, "nation").join(F.broadcast(t(spark, sf_dir, "region")), F.col("n_regionkey") == F.col("r_regionkey")).select(F.col("n_nationkey").cast("bigint").alias("k"), "r_name")
    e = windows.replay(spark, sf_dir).withColumn("k", F.pmod("user_id", F.lit(25)))
    out = windows.run_to_table(windows.against_table(e, dim, "k").select("event_id", "r_name"), "append")
    return out.groupBy("r_name").agg(F.count("*").alias("n"))


@query("SELECT count(*) AS pairs FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def stream_stream_join(spark, sf_dir):
    e = windows.replay(spark, sf_dir)
    joined = windows.within(e.filter("event_type = 'click'"), windows.replay(spark, sf_dir).filter("event_type = 'purchase'"), "user_id", "1 hour")
    out = windows.run_to_table(joined.select(F.col("a.event_id").alias("a"), F.col("b.event_id").alias("b")), "append")
    return out.agg(F.count("*").alias("pairs"))


@query("SELECT count(*) AS kept, 0 AS late FROM events")
def stream_in_order_keeps_all(spark, sf_dir):
    """Three files in time order: nothing is behind the watermark (rows that no window counted are the late ones)."""
    e = t(spark, sf_dir, "events")
    path = windows.split_files(e, 3, "ts")
    out = windows.run_to_table(windows.tumbling(windows.file_stream(spark, path, windows.EVENTS)), "update")
    return _kept_and_late(out, e)


@query("SELECT count(*) FILTER (ts >= top - INTERVAL 5 DAY) AS kept, CAST(count(*) FILTER (ts < top - INTERVAL 5 DAY) AS INTEGER) AS late FROM events CROSS JOIN (SELECT max(ts) AS top FROM events)")
def stream_late_rows(spark, sf_dir):
    """The last five days come first, in two micro-batches: every earlier row is behind the watermark by then and is left out."""
    e = t(spark, sf_dir, "events")
    cut = e.agg((F.max("ts") - F.expr("INTERVAL 5 DAYS")).alias("cut"))
    sided = e.crossJoin(F.broadcast(cut)).withColumn("old", F.col("ts") < F.col("cut")).drop("cut")
    path = windows.files_in_turn([sided.filter(c).drop("old") for c in ("not old and event_id % 2 = 0", "not old and event_id % 2 <> 0", "old")])
    out = windows.run_to_table(windows.tumbling(windows.file_stream(spark, path, windows.EVENTS)), "update")
    return _kept_and_late(out, e)


def _kept_and_late(out, events):
    """Rows that the last state of each window counts, and all others of the input."""
    last = out.groupBy("w", "event_type").agg(F.max_by("n", "_batch").alias("n")).agg(F.coalesce(F.sum("n"), F.lit(0)).alias("kept"))
    return last.crossJoin(events.agg(F.count("*").alias("n"))).select("kept", (F.col("n") - F.col("kept")).cast("int").alias("late"))


@query("SELECT 300 AS w, 20 AS most, CAST(44850 AS BIGINT) AS ids")
def stream_rate_points(spark, sf_dir):
    """One micro-batch of 300 points from a rate stream through the summary log."""
    pts = windows.rate_points(spark, 300, 8)
    out, check = scratch_path(spark, "rate_log"), scratch_path(spark, "rate_checkpoint")
    seen = scratch_path(spark, "rate_rows")
    write = log.summary_writer(out, 2, 50, None, 20)

    def both(df, batch_id):
        write(df, batch_id)
        df.select("id").write.mode("overwrite").parquet(f"{seen}/batch={batch_id}")

    pts.writeStream.foreachBatch(both).option("checkpointLocation", check).trigger(once=True).start().awaitTermination()
    ids = spark.read.schema("id bigint").option("recursiveFileLookup", "true").parquet(seen).agg(F.sum("id").alias("ids"))
    s = log.compact(spark, out, 20).agg(F.sum("w").alias("w"), F.when(F.count("*") <= 20, 20).otherwise(F.count("*")).alias("most"))
    return s.crossJoin(ids)


@query("SELECT count(*) AS w, true AS small FROM events")
def stream_summary_invariants(spark, sf_dir):
    """The summary log over four micro-batches keeps the weight; its compaction stays small."""
    pts = points.event_points(spark, sf_dir).select("id", "x", "w")
    path = windows.split_files(pts, 4, "id")
    out, check = scratch_path(spark, "summary_log"), scratch_path(spark, "summary_log_checkpoint")
    log.summarize_stream(windows.file_stream(spark, path, "id bigint, x array<double>, w bigint"), out, check, 5, 250, 100, 6).awaitTermination()
    return log.compact(spark, out, 100).agg(F.sum("w").alias("w"), (F.count("*") <= 100).alias("small"))


@query("SELECT count(*) AS n, true AS bounded FROM events")
def stream_keyed_state(spark, sf_dir):
    """Live summaries in state: the last row of each shard counts all its points."""
    pts = points.event_points(spark, sf_dir).select("id", "x", "w")
    path = windows.split_files(pts, 3, "id")
    live = keyed.live_summary(windows.file_stream(spark, path, "id bigint, x array<double>, w bigint"), 4, 80)
    out = windows.run_to_table(live, "update")
    last = out.groupBy("shard").agg(F.max_by("n", "_batch").alias("n"), F.max("features").alias("f"))
    return last.agg(F.sum("n").alias("n"), (F.max("f") <= 80).alias("bounded"))
