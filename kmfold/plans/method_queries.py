"""Queries of the methods, with DuckDB SQL for their values or for what any right run must return."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from kmfold.functions import cost, features
from kmfold.functions.hashing import arithmetic_hash
from kmfold.functions.vectors import lattice, squared_length
from kmfold.operators import baselines, clustering, linalg, measures, summaries
from kmfold.plans import pieces
from kmfold.plans.pieces import TreeParams
from kmfold.sources import generators, points
from kmfold.staging import stage

Q: dict = {}
SQL: dict[str, str] = {}
PRIME = 2147483647


def query(sql: str | None = None):
    def add(f):
        Q[f.__name__] = f
        if sql is not None:
            SQL[f.__name__] = sql
        return f

    return add


def grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Embeddings on the integer lattice: sums are exact in doubles."""
    e = points.emb64(spark, sf_dir)
    return e.select("id", F.transform(lattice("x"), lambda v: v.cast("double")).alias("x"), "w", "label")


def matrices(pts: DataFrame, rows: int = 100_000):
    """The whole table as matrices of near equal size, of about ``rows`` rows at most."""
    dealt = pieces.by_hash(pts, max(1, -(-pts.count() // rows)))
    for r in dealt.select("piece").distinct().orderBy("piece").collect():
        yield points.matrix(dealt.filter(F.col("piece") == r["piece"]))


#: Lattice rows, lattice rows by coordinate, and fixed centers, as SQL.
LAT = "lat AS (SELECT vec_id AS id, label, list_transform(embedding, lambda v: CAST(round(CAST(v AS DOUBLE) * 1000) AS BIGINT)) AS x FROM embeddings)"
DIM = LAT + ", dim AS (SELECT id, label, generate_subscripts(x, 1) - 1 AS dim, unnest(x) AS v FROM lat)"
D2 = "list_sum(list_transform(range(1, 65), lambda i: (a.x[i] - c.x[i]) * (a.x[i] - c.x[i])))"
FIXED = (0, 100, 200, 300, 400)
CEN = LAT + ", cen AS (SELECT id // 100 AS cid, x FROM lat WHERE id IN (0, 100, 200, 300, 400))"
NEAR = CEN + f", near AS (SELECT id, label, cid, d2 FROM (SELECT a.id, a.label, c.cid, CAST({D2} AS BIGINT) AS d2, row_number() OVER (PARTITION BY a.id ORDER BY {D2}, c.cid) AS r FROM lat a CROSS JOIN cen c) WHERE r = 1)"


def fixed_centers(spark: SparkSession, sf_dir: str) -> list:
    rows = grid(spark, sf_dir).filter(F.col("id").isin(*FIXED)).orderBy("id").collect()
    return [(int(r["id"]) // 100, list(r["x"])) for r in rows]


def long(c):
    return F.round(c).cast("bigint")


# --- clustering features -------------------------------------------------------------


@query(f"WITH {DIM} SELECT label, dim, count(*) AS w, CAST(sum(v) AS BIGINT) AS ls, CAST(sum(v * v) AS BIGINT) AS ss_dim FROM dim GROUP BY label, dim")
def cf_by_label(spark, sf_dir):
    g = grid(spark, sf_dir)
    one = features.cf_agg(g, ["label"])
    sq = features.cf_agg(g.withColumn("x", F.transform("x", lambda v: v * v)), ["label"])
    both = one.join(sq.withColumnRenamed("cf", "sq"), "label")
    z = both.select("label", F.col("cf.w").alias("w"), F.posexplode(F.arrays_zip(F.col("cf.ls").alias("a"), F.col("sq.ls").alias("b"))).alias("dim", "z"))
    return z.select("label", F.col("dim").cast("bigint").alias("dim"), "w", long(F.col("z.a")).alias("ls"), long(F.col("z.b")).alias("ss_dim"))


@query(f"WITH {DIM} SELECT label, count(*) // 64 AS w, CAST(sum(v) AS BIGINT) AS ls_total, CAST(sum(v * v) AS BIGINT) AS ss FROM dim GROUP BY label")
def cf_merge_two_levels(spark, sf_dir):
    small = features.cf_agg(grid(spark, sf_dir).withColumn("g", F.pmod("id", F.lit(7))), ["label", "g"])
    out = features.cf_merge(small, ["label"])
    return out.select("label", F.col("cf.w").alias("w"), long(F.aggregate("cf.ls", F.lit(0.0), lambda s, v: s + v)).alias("ls_total"), long(F.col("cf.ss")).alias("ss"))


@query(f"WITH {LAT}, c AS (SELECT x FROM lat WHERE id = 0) SELECT a.label, CAST(sum({D2}) AS BIGINT) AS cost FROM lat a CROSS JOIN c GROUP BY a.label")
def cf_cost_fixed_center(spark, sf_dir):
    center = F.array(*map(F.lit, fixed_centers(spark, sf_dir)[0][1]))
    return features.cf_agg(grid(spark, sf_dir), ["label"]).select("label", long(features.cf_cost(F.col("cf"), center)).alias("cost"))


@query(f"WITH {DIM}, s AS (SELECT label, dim, count(*) AS n, sum(v) AS ls, sum(v * v) AS ss FROM dim GROUP BY label, dim) SELECT label, CAST(sum(n * ss) - sum(ls * ls) AS BIGINT) AS scaled_within FROM s GROUP BY label")
def cf_within(spark, sf_dir):
    cf = F.col("cf")
    return features.cf_agg(grid(spark, sf_dir), ["label"]).select("label", long(features.cf_within(cf) * cf["w"]).alias("scaled_within"))


@query(f"WITH {LAT}, c AS (SELECT x FROM lat WHERE id = 0), n AS (SELECT label, count(*) AS n FROM lat GROUP BY label) SELECT a.label, CAST(n.n * sum({D2}) AS BIGINT) AS left_side, CAST(n.n * sum({D2}) AS BIGINT) AS right_side FROM lat a CROSS JOIN c JOIN n ON n.label = a.label GROUP BY a.label, n.n")
def centroid_identity(spark, sf_dir):
    """Cost to any center is the weight times the squared distance from the centroid plus the inner cost."""
    c = F.array(*map(F.lit, fixed_centers(spark, sf_dir)[0][1]))
    cf = F.col("cf")
    away = F.aggregate(F.zip_with(F.transform(cf["ls"], lambda v: F.round(v)), c, lambda a, b: (a - cf["w"] * b) * (a - cf["w"] * b)), F.lit(0.0), lambda s, v: s + v)
    return features.cf_agg(grid(spark, sf_dir), ["label"]).select("label", long(cf["w"] * features.cf_cost(cf, c)).alias("left_side"), long(away + cf["w"] * cf["ss"] - squared_length(F.transform(cf["ls"], lambda v: F.round(v)))).alias("right_side"))


@query(f"WITH {DIM} SELECT label, count(*) AS w, CAST(round(avg(v) * 1000000) AS BIGINT) AS mean FROM dim WHERE dim = 0 GROUP BY label")
def centroid_first_coordinate(spark, sf_dir):
    return features.centroid(grid(spark, sf_dir), ["label"]).select("label", "w", long(F.col("x")[0] * 1000000).alias("mean"))


@query("SELECT l_linenumber, count(*) AS n, CAST(sum(CAST(round(CAST(l_linenumber AS DOUBLE) * l_quantity / (l_linenumber + l_quantity) * l_extendedprice) AS BIGINT)) AS BIGINT) AS exact_increase, CAST(sum(CAST(round(l_quantity * l_extendedprice) AS BIGINT)) AS BIGINT) AS naive_increase FROM lineitem GROUP BY l_linenumber")
def insert_increase_grid(spark, sf_dir):
    t = points.table(spark, sf_dir, "lineitem").select("l_linenumber", "l_quantity", "l_extendedprice")
    s, w, d = F.col("l_linenumber"), F.col("l_quantity"), F.col("l_extendedprice")
    return t.groupBy("l_linenumber").agg(F.count("*").alias("n"), F.sum(long(features.insert_increase(s, w, d))).alias("exact_increase"), F.sum(long(features.insert_increase(s, w, d, "naive"))).alias("naive_increase"))


_COPIES = "CASE WHEN slack <= 0 THEN w ELSE greatest(0, least(w, CAST(floor((s * t - s * c) / slack) AS BIGINT))) END"


@query(f"WITH g AS (SELECT CAST(l_quantity AS BIGINT) AS w, CAST(l_linenumber * 3 AS DOUBLE) AS s, l_discount * 100 AS c, floor(l_extendedprice / 10000) AS d, floor(l_tax * 1000) + 8 AS t FROM lineitem), k AS (SELECT *, s * d - t + c AS slack FROM g), f AS (SELECT w, {_COPIES} AS fit FROM k) SELECT CASE WHEN fit = w THEN 'all' WHEN fit = 0 THEN 'none' ELSE 'part' END AS outcome, count(*) AS n, CAST(sum(fit) AS BIGINT) AS copies FROM f GROUP BY 1")
def max_copies_grid(spark, sf_dir):
    t = points.table(spark, sf_dir, "lineitem")
    g = t.select(F.col("l_quantity").cast("bigint").alias("w"), (F.col("l_linenumber") * 3).cast("double").alias("s"), (F.col("l_discount") * 100).alias("c"), F.floor(F.col("l_extendedprice") / 10000).cast("double").alias("d"), (F.floor(F.col("l_tax") * 1000) + 8).cast("double").alias("t"))
    f = g.select("w", features.max_copies(F.col("w"), F.col("s"), F.col("c"), F.col("d"), F.col("t")).alias("fit"))
    kind = F.when(F.col("fit") == F.col("w"), "all").when(F.col("fit") == 0, "none").otherwise("part")
    return f.groupBy(kind.alias("outcome")).agg(F.count("*").alias("n"), F.sum("fit").alias("copies"))


@query("SELECT w, s, c, d, t, fit FROM (VALUES (10, 4, 2.0, 3.0, 8.0, 4), (10, 4, 2.0, 1.0, 8.0, 10), (7, 1, 0.0, 10.0, 1.0, 0), (3, 4, 2.0, 3.0, 8.0, 3), (5, 2, 1.0, 0.0, 1.0, 5)) v(w, s, c, d, t, fit)")
def threshold_cases(spark, sf_dir):
    """Worked cases: part of the copies, all, none, the boundary reached exactly, and equal points."""
    rows = spark.createDataFrame([(10, 4, 2.0, 3.0, 8.0), (10, 4, 2.0, 1.0, 8.0), (7, 1, 0.0, 10.0, 1.0), (3, 4, 2.0, 3.0, 8.0), (5, 2, 1.0, 0.0, 1.0)], "w int, s int, c double, d double, t double")
    return rows.withColumn("fit", features.max_copies(F.col("w"), F.col("s"), F.col("c"), F.col("d"), F.col("t")).cast("int"))


# --- assignment, cost, Lloyd, seeding --------------------------------------------------


@query(f"WITH {NEAR} SELECT id, CAST(cid AS INTEGER) AS cid, d2 FROM near")
def assign_fixed_centers(spark, sf_dir):
    out = cost.assign(grid(spark, sf_dir), fixed_centers(spark, sf_dir))
    return out.select("id", "cid", F.col("d2").cast("bigint").alias("d2"))


@query(f"WITH {NEAR} SELECT id, CAST(cid AS INTEGER) AS cid, d2 FROM near")
def assign_vectorized(spark, sf_dir):
    out = cost.assign(grid(spark, sf_dir), fixed_centers(spark, sf_dir), vectorized=True)
    return out.select("id", "cid", F.col("d2").cast("bigint").alias("d2"))


@query(f"WITH {NEAR} SELECT CAST(sum(d2) AS BIGINT) AS cost, count(*) AS n FROM near")
def cost_fixed_centers(spark, sf_dir):
    out = cost.kmeans_cost(grid(spark, sf_dir), fixed_centers(spark, sf_dir))
    return out.select(F.col("cost").cast("bigint").alias("cost"), "n")


@query(f"WITH {NEAR} SELECT CAST(sum(d2 * (id % 5 + 1)) AS BIGINT) AS cost, CAST(sum(id % 5 + 1) AS BIGINT) AS weight FROM near")
def cost_weighted(spark, sf_dir):
    rows = grid(spark, sf_dir).withColumn("w", F.pmod("id", F.lit(5)) + 1)
    return cost.kmeans_cost(rows, fixed_centers(spark, sf_dir)).select(F.col("cost").cast("bigint").alias("cost"), "weight")


@query(f"WITH {NEAR}, dim AS (SELECT id, generate_subscripts(x, 1) - 1 AS dim, unnest(x) AS v FROM lat) SELECT CAST(n.cid AS INTEGER) AS cid, d.dim, count(*) AS w, CAST(sum(v) AS BIGINT) AS ls FROM near n JOIN dim d USING (id) GROUP BY n.cid, d.dim")
def lloyd_one_step(spark, sf_dir):
    g, held = grid(spark, sf_dir), fixed_centers(spark, sf_dir)
    cf = features.cf_agg(cost.assign(g, held), ["cid"])
    return cf.select("cid", F.col("cf.w").alias("w"), F.posexplode("cf.ls").alias("dim", "v")).select("cid", F.col("dim").cast("bigint").alias("dim"), "w", long(F.col("v")).alias("ls"))


def _three_steps() -> str:
    parts = [CEN.replace("cen AS", "cen0 AS")]
    for k in range(3):
        near = f"near{k} AS (SELECT id, cid FROM (SELECT a.id, c.cid, row_number() OVER (PARTITION BY a.id ORDER BY {D2}, c.cid) AS r FROM lat a CROSS JOIN cen{k} c) WHERE r = 1)"
        dims = f"mean{k} AS (SELECT n.cid, generate_subscripts(l.x, 1) AS i, unnest(l.x) AS v FROM near{k} n JOIN lat l USING (id))"
        nxt = f"cen{k + 1} AS (SELECT cid, list(m ORDER BY i) AS x FROM (SELECT cid, i, CAST(round(sum(v) / count(*)) AS BIGINT) AS m FROM mean{k} GROUP BY cid, i) GROUP BY cid)"
        parts += [near, dims, nxt]
    return "WITH " + ", ".join(parts) + " SELECT CAST(cid AS INTEGER) AS cid, generate_subscripts(x, 1) - 1 AS dim, unnest(x) AS v FROM cen3"


@query(_three_steps())
def lloyd_three_steps(spark, sf_dir):
    """Means are rounded to the lattice after each step, on both sides."""
    g, held = grid(spark, sf_dir), fixed_centers(spark, sf_dir)
    for _ in range(3):
        cf = features.cf_agg(cost.assign(g, held), ["cid"])
        rows = cf.select("cid", F.transform("cf.ls", lambda v: F.round(F.round(v) / F.col("cf.w"))).alias("c")).orderBy("cid").collect()
        held = [(r["cid"], list(r["c"])) for r in rows]
    rows = clustering.centers_frame(spark, held).select("cid", F.posexplode("c").alias("dim", "v"))
    return rows.select("cid", F.col("dim").cast("bigint").alias("dim"), F.col("v").cast("bigint").alias("v"))


@query("SELECT 0 AS rises")
def lloyd_monotone(spark, sf_dir):
    _, history = clustering.lloyd(grid(spark, sf_dir), fixed_centers(spark, sf_dir), max_iter=8, tol=0.0)
    rows = spark.createDataFrame([(i, c) for i, c in enumerate(history)], "i int, cost double")
    before = F.lag("cost").over(clustering.Window.orderBy("i"))  # one row an iteration
    return rows.withColumn("b", before).agg(F.sum(F.when(F.col("cost") > F.col("b"), 1).otherwise(0)).cast("int").alias("rises"))


def _hash(key: str, seed: str | int) -> str:
    """Three quadratic rounds as nested list reductions."""
    return f"list_reduce([CAST({key} AS BIGINT) + 1, 40503, 69069, 1013904223], lambda h, c: (h * h + c * h + {seed}) % {PRIME})"


@query(f"SELECT vec_id AS id, CAST({_hash('vec_id', 1)} AS BIGINT) AS h FROM embeddings")
def hash_agrees(spark, sf_dir):
    return points.emb64(spark, sf_dir).select("id", arithmetic_hash(F.col("id"), 1).alias("h"))


@query(f"SELECT vec_id AS id FROM embeddings ORDER BY {_hash('vec_id', 1)}, vec_id LIMIT 5")
def uniform_seeding(spark, sf_dir):
    e = points.emb64(spark, sf_dir)
    seeds = clustering.centers_frame(spark, clustering.uniform_seeds(e, 5, 1))
    return e.join(F.broadcast(seeds), e["x"] == seeds["c"]).select("id")


def _d2_sql(k: int) -> str:
    u = lambda s: f"((({_hash('a.id', s)} / 2147483647.0) * (2147483647.0 - 1) + 1) / 2147483648.0)"
    parts = [LAT, f"s0 AS (SELECT id, x FROM lat ORDER BY {_hash('id', 1)}, id LIMIT 1)"]
    for i in range(1, k):
        held = " UNION ALL ".join(f"SELECT * FROM s{j}" for j in range(i))
        parts.append(f"d{i} AS (SELECT a.id, CAST(min({D2}) AS DOUBLE) AS d2 FROM lat a CROSS JOIN ({held}) c GROUP BY a.id)")
        parts.append(f"s{i} AS (SELECT a.id, a.x FROM lat a JOIN d{i} d ON d.id = a.id WHERE d.d2 > 0 ORDER BY -ln({u(1 + i)}) / d.d2, a.id LIMIT 1)")
    return "WITH " + ", ".join(parts) + " " + " UNION ALL ".join(f"SELECT {j} AS cid, id FROM s{j}" for j in range(k))


@query(_d2_sql(5))
def d2_seeding_k5(spark, sf_dir):
    g = grid(spark, sf_dir)
    seeds = clustering.centers_frame(spark, clustering.d2_seeds(g, 5, 1))
    return g.join(F.broadcast(seeds), g["x"] == seeds["c"]).select("cid", "id")


@query("SELECT 5 AS k, true AS below_one_center, true AS not_above_seeds")
def kmeanspp_full(spark, sf_dir):
    g = grid(spark, sf_dir)
    centers, history = clustering.kmeanspp(g, 5, max_iter=5)
    total = features.cf_agg(g).select(features.cf_within(F.col("cf")).alias("c")).first()["c"]
    rows = [(len(centers), bool(history[-1] <= total), bool(history[-1] <= history[0]))]
    return spark.createDataFrame(rows, "k int, below_one_center boolean, not_above_seeds boolean")


@query("SELECT 5 AS k, true AS below_one_center, true AS near_ours")
def library_second_opinion(spark, sf_dir):
    e = points.emb64(spark, sf_dir)
    theirs = cost.cost_value(e, clustering.library_kmeans(e, 5))
    _, ours = clustering.kmeanspp(e, 5, max_iter=10)
    total = features.cf_agg(e).select(features.cf_within(F.col("cf")).alias("c")).first()["c"]
    return spark.createDataFrame([(5, theirs <= total, 0.85 <= theirs / ours[-1] <= 1.15)], "k int, below_one_center boolean, near_ours boolean")


@query("WITH t AS (SELECT vec_id % 10 AS cid, label, count(*) AS n FROM embeddings GROUP BY ALL), c AS (SELECT cid, max(n) AS top, sum(n) AS n FROM t GROUP BY cid), l AS (SELECT label, sum(n) AS n FROM t GROUP BY label) SELECT (SELECT sum(top) / sum(n) FROM c) AS purity, CAST((SELECT sum(n * (n - 1) // 2) FROM c) AS BIGINT) AS pairs_cluster, CAST((SELECT sum(n * (n - 1) // 2) FROM l) AS BIGINT) AS pairs_label, CAST((SELECT sum(n * (n - 1) // 2) FROM t) AS BIGINT) AS pairs_both")
def label_agreement(spark, sf_dir):
    return clustering.agreement(points.emb64(spark, sf_dir).withColumn("cid", F.pmod("id", F.lit(10))))


@query("""WITH s AS (SELECT s_suppkey, CAST(s_nationkey AS DOUBLE) AS a, s_acctbal / 1000 AS b, row_number() OVER (ORDER BY s_suppkey) - 1 AS i FROM supplier ORDER BY s_suppkey LIMIT 10),
p AS (SELECT range AS mask FROM range(512)), g AS (SELECT mask, (mask >> i) & 1 AS side, count(*) AS n, sum(a) AS sa, sum(b) AS sb, sum(a * a + b * b) AS ss FROM p CROSS JOIN s GROUP BY ALL)
SELECT round(min(cost), 6) AS optimum FROM (SELECT mask, sum(ss - (sa * sa + sb * sb) / n) AS cost FROM g GROUP BY mask)""")
def brute_force_optimum(spark, sf_dir):
    """All partitions of the first ten suppliers in two parts (a fixture of ten rows)."""
    s = points.table(spark, sf_dir, "supplier").orderBy("s_suppkey").limit(10)
    x = points.matrix(s.select(F.col("s_suppkey").alias("id"), F.array(F.col("s_nationkey").cast("double"), F.col("s_acctbal") / 1000).alias("x")))
    return spark.createDataFrame([(baselines.brute_force(x, 2),)], "optimum double").select(F.round("optimum", 6).alias("optimum"))


# --- pieces and tree plans -------------------------------------------------------------


@query("SELECT vec_id // 50 AS piece, count(*) AS n FROM embeddings GROUP BY 1")
def piece_ids(spark, sf_dir):
    return pieces.by_key(points.emb64(spark, sf_dir), 50).groupBy("piece").agg(F.count("*").alias("n"))


@query("WITH r AS (SELECT l_linenumber, row_number() OVER (ORDER BY l_orderkey, l_linenumber, l_partkey, l_suppkey, l_quantity, l_extendedprice, l_discount, l_tax, l_shipdate, l_returnflag, l_linestatus) - 1 AS id FROM lineitem) SELECT count(*) AS n, min(id) AS low, max(id) AS high, count(DISTINCT id) AS ids, CAST(sum(id * l_linenumber) AS BIGINT) AS in_order FROM r")
def dense_index_counts(spark, sf_dir):
    d = pieces.dense_index(points.table(spark, sf_dir, "lineitem").select(*points.LINE_ORDER), points.LINE_ORDER)
    return d.agg(F.count("*").alias("n"), F.min("id").alias("low"), F.max("id").alias("high"), F.countDistinct("id").alias("ids"), F.sum(F.col("id") * F.col("l_linenumber")).alias("in_order"))


@query("SELECT CAST(epoch(date_trunc('day', ts)) AS BIGINT) AS piece, count(*) AS n FROM events GROUP BY 1")
def time_pieces(spark, sf_dir):
    return pieces.by_time(points.table(spark, sf_dir, "events").select("event_id", "ts"), "ts", "1 day").groupBy("piece").agg(F.count("*").alias("n"))


@query("SELECT count(*) AS n, 16 AS pieces, true AS near_equal FROM embeddings")
def hash_pieces(spark, sf_dir):
    g = pieces.by_hash(points.emb64(spark, sf_dir), 16).groupBy("piece").agg(F.count("*").alias("m"))
    return g.agg(F.sum("m").alias("n"), F.count("*").cast("int").alias("pieces"), (F.max("m") < 4 * F.min("m")).alias("near_equal"))


_TREE = """WITH RECURSIVE lv(name, level, pieces, fan, nodes) AS (
SELECT name, 0, CAST(ceil(n / ps) AS BIGINT), fan, CAST(ceil(ceil(n / ps) / fan) AS BIGINT) FROM (SELECT 'illustration' AS name, 45.0 AS n, 5 AS ps, 3 AS fan UNION ALL SELECT 'entry', 500.0, 50, 3 UNION ALL SELECT 'embeddings', (SELECT count(*) FROM embeddings), 25, 4 UNION ALL SELECT 'events', (SELECT count(*) FROM events), 100, 10)
UNION ALL SELECT name, level + 1, nodes, fan, CAST(ceil(nodes / fan) AS BIGINT) FROM lv WHERE nodes > 1)
"""


@query(_TREE + "SELECT name, CAST(level AS INTEGER) AS level, pieces, nodes FROM lv")
def tree_plan_counts(spark, sf_dir):
    cases = [("illustration", 45, 5, 3), ("entry", 500, 50, 3), ("embeddings", points.table(spark, sf_dir, "embeddings").count(), 25, 4), ("events", points.table(spark, sf_dir, "events").count(), 100, 10)]
    rows = [(name, lv["level"], lv["pieces"], lv["nodes"]) for name, n, ps, fan in cases for lv in pieces.plan_levels(n, TreeParams(l=1, ps=ps, np=fan))]
    return spark.createDataFrame(rows, "name string, level int, pieces bigint, nodes bigint")


@query(_TREE + "SELECT name, CAST(sum(pieces) AS BIGINT) AS svds, CAST(sum(nodes) AS BIGINT) AS runs, CAST(count(*) AS INTEGER) AS levels FROM lv GROUP BY name")
def tree_total_counts(spark, sf_dir):
    cases = [("illustration", 45, 5, 3), ("entry", 500, 50, 3), ("embeddings", points.table(spark, sf_dir, "embeddings").count(), 25, 4), ("events", points.table(spark, sf_dir, "events").count(), 100, 10)]
    rows = []
    for name, n, ps, fan in cases:
        c = pieces.tree_counts(n, TreeParams(l=1, ps=ps, np=fan))
        rows.append((name, c["svds"], c["runs"], c["levels"]))
    return spark.createDataFrame(rows, "name string, svds bigint, runs bigint, levels int")


@query("WITH RECURSIVE p(piece, level, node) AS (SELECT range, 0, range // 3 FROM range(9) UNION ALL SELECT piece, level + 1, node // 3 FROM p WHERE level < 1) SELECT piece, CAST(level AS INTEGER) AS level, node FROM p")
def tree_paths(spark, sf_dir):
    return spark.sql("WITH RECURSIVE p(piece, level, node) AS (SELECT id, 0, id DIV 3 FROM range(9) UNION ALL SELECT piece, level + 1, node DIV 3 FROM p WHERE level < 1) SELECT piece, level, node FROM p")


@query("SELECT CAST(ceil(count(*) / 50.0) AS BIGINT) - 1 AS chain_first_piece, CAST(ceil(log2(ceil(count(*) / 50.0))) AS BIGINT) + 1 AS tree_each_point FROM embeddings")
def chain_against_tree(spark, sf_dir):
    """Reductions of the first piece in a chain, and of every point in a binary tree."""
    n = points.table(spark, sf_dir, "embeddings").count()
    tree = pieces.tree_counts(n, TreeParams(l=1, ps=50, np=[1, 2], project_levels="none"))
    return spark.createDataFrame([(pieces.chain_counts(n, 50)["reductions_first_piece"], tree["reductions_per_point"])], "chain_first_piece bigint, tree_each_point bigint")


# --- linear algebra ----------------------------------------------------------------------


@query(f"WITH {DIM} SELECT a.dim AS i, b.dim AS j, CAST(sum(a.v * b.v) AS BIGINT) AS g FROM dim a JOIN dim b USING (id) GROUP BY a.dim, b.dim")
def gram_matrix(spark, sf_dir):
    rows = linalg.gram_rows(grid(spark, sf_dir)).select(F.col("i").cast("bigint").alias("i"), F.posexplode("g").alias("j", "g"))
    return rows.select("i", F.col("j").cast("bigint").alias("j"), long(F.col("g")).alias("g"))


@query(f"WITH {DIM}, rep AS (SELECT id, dim, v, unnest(range(id % 3 + 1)) AS copy FROM dim) SELECT a.dim AS i, b.dim AS j, CAST(sum(a.v * b.v) AS BIGINT) AS g FROM rep a JOIN rep b ON a.id = b.id AND a.copy = b.copy WHERE a.dim < 16 AND b.dim < 16 GROUP BY a.dim, b.dim")
def weighted_gram_equals_replicated(spark, sf_dir):
    g = grid(spark, sf_dir).withColumn("w", F.pmod("id", F.lit(3)) + 1).withColumn("x", F.slice("x", 1, 16))
    rows = linalg.gram_rows(g).select(F.col("i").cast("bigint").alias("i"), F.posexplode("g").alias("j", "g"))
    return rows.select("i", F.col("j").cast("bigint").alias("j"), long(F.col("g")).alias("g"))


@query(f"WITH {DIM} SELECT count(*) // 64 AS n, CAST(sum(v * v) AS BIGINT) AS total FROM dim")
def frobenius_total(spark, sf_dir):
    return grid(spark, sf_dir).agg(F.count("*").alias("n"), F.sum(squared_length("x")).cast("bigint").alias("total"))


@query(f"""WITH {DIM}, walsh AS (SELECT r.range AS c, s.range AS dim, CASE WHEN bit_count(CAST(r.range & s.range AS BIGINT)) % 2 = 0 THEN 1 ELSE -1 END AS h FROM range(8) r CROSS JOIN range(64) s),
co AS (SELECT id, c, sum(v * h) AS y FROM dim JOIN walsh USING (dim) GROUP BY id, c) SELECT w.dim, CAST(sum(y * h) AS BIGINT) AS scaled FROM co JOIN walsh w USING (c) GROUP BY w.dim""")
def projection_fixed_basis(spark, sf_dir):
    """Projection on eight Walsh functions: exact in binary, 64 times the coordinate sums are whole."""
    import numpy as np

    v = np.array([[(-1.0) ** bin(c & j).count("1") / 8.0 for j in range(64)] for c in range(8)])
    out = linalg.project_global(grid(spark, sf_dir), v)
    return out.select(F.posexplode("x").alias("dim", "v")).groupBy(F.col("dim").cast("bigint").alias("dim")).agg(long(F.sum(F.col("v") * 64)).alias("scaled"))


@query("SELECT round(sum(list_sum(list_transform(embedding, lambda v: CAST(v AS DOUBLE) * v))), 3) AS energy, 64 AS directions, true AS falling FROM embeddings")
def spectrum_embeddings(spark, sf_dir):
    s = linalg.spectrum(points.emb64(spark, sf_dir))
    before = F.lag("sigma").over(clustering.Window.orderBy("rank"))  # one row a direction
    return s.withColumn("b", before).agg(F.round(F.sum(F.col("sigma") * F.col("sigma")), 3).alias("energy"), F.count("*").cast("int").alias("directions"), F.every(F.coalesce(F.col("sigma") <= F.col("b"), F.lit(True))).alias("falling"))


@query("SELECT l, true AS between, true AS falls FROM (VALUES (5), (10), (20), (40)) v(l)")
def residual_rank_l(spark, sf_dir):
    e = points.emb64(spark, sf_dir)
    total = e.agg(F.sum(squared_length("x"))).first()[0]
    out, last = [], total
    for l in (5, 10, 20, 40):  # noqa: E741
        moved = linalg.project(pieces.by_key(e, 250), l, kind="exact").agg(F.sum("moved")).first()[0]
        out.append((l, 0 <= moved <= total, moved <= last))
        last = moved
    return spark.createDataFrame(out, "l int, between boolean, falls boolean")


@query("SELECT kind, l, true AS not_below_optimum, true AS close FROM (VALUES ('gram'), ('random'), ('random2')) k(kind) CROSS JOIN (VALUES (10), (15), (20), (30), (50)) v(l)")
def svd_random_vs_exact(spark, sf_dir):
    """Five seeds each: deviation from the best residual of the same rank is never negative, and below 7 percent."""
    told = {(kind, l): [] for kind in ("gram", "random", "random2") for l in (10, 15, 20, 30, 50)}
    for x in matrices(points.emb64(spark, sf_dir)):
        for kind, l in told:  # noqa: E741
            told[kind, l] += linalg.svd_comparison(x, l, range(5), kind)
    rows = [(kind, l, all(t["percent"] >= -1e-6 for t in ts), all(t["percent"] < 7 for t in ts)) for (kind, l), ts in told.items()]
    return spark.createDataFrame(rows, "kind string, l int, not_below_optimum boolean, close boolean")


@query("SELECT true AS same_subspace, true AS multiplied_differs")
def weighted_subspace(spark, sf_dir):
    """Root-of-weight scaling gives the subspace of the replicated rows; multiplied rows give another."""
    import numpy as np

    e = grid(spark, sf_dir).withColumn("w", F.pmod("id", F.lit(4)) + 1)
    same, differs = [], []
    for m in matrices(e.withColumn("x", F.concat("x", F.array(F.col("w").cast("double"))))):
        x, w = m[:, :-1], m[:, -1]
        _, a = linalg.svd_exact(x * np.sqrt(w)[:, None], 8)
        _, b = linalg.svd_exact(np.repeat(x, w.astype(int), axis=0), 8)
        _, c = linalg.svd_exact(x * w[:, None], 8)
        same.append(bool(np.abs(a.T @ a - b.T @ b).max() < 1e-8))
        differs.append(bool(np.abs(a.T @ a - c.T @ c).max() > 1e-4))
    return spark.createDataFrame([(all(same), all(differs))], "same_subspace boolean, multiplied_differs boolean")


@query("SELECT k, rule, l FROM (VALUES (10, 'k', 10), (10, '1.5k', 15), (10, 'k/eps', 100), (50, 'k', 50), (50, '1.5k', 64), (50, 'k/eps', 64)) v(k, rule, l)")
def target_dimensions(spark, sf_dir):
    rows = []
    for k, d in ((10, None), (50, 64)):
        for rule in ("k", "1.5k", "k/eps"):
            rows.append((k, rule, linalg.target_dim(k, None, d, 0.1, rule)))
    return spark.createDataFrame(rows, "k int, rule string, l int")


@query("SELECT true AS sketch_holds_the_energy, true AS orthonormal")
def global_basis_sketch(spark, sf_dir):
    import numpy as np

    e = points.emb64(spark, sf_dir)
    s, _ = linalg.global_basis(e, 10)
    t, v = linalg.global_basis(e, 10, method="sketch")
    return spark.createDataFrame([(bool((t**2).sum() >= 0.9 * (s**2).sum()), bool(np.abs(v @ v.T - np.eye(10)).max() < 1e-9))], "sketch_holds_the_energy boolean, orthonormal boolean")


# --- summaries -------------------------------------------------------------------------------


def _sums(summary: DataFrame) -> DataFrame:
    return summary.select("w", F.posexplode("x").alias("dim", "v")).groupBy(F.col("dim").cast("bigint").alias("dim")).agg(F.sum("w").alias("w"), long(F.sum(F.col("w") * F.col("v"))).alias("ls"))


@query(f"WITH {DIM} SELECT dim, count(*) AS w, CAST(sum(v) AS BIGINT) AS ls FROM dim GROUP BY dim")
def direct_summary_sums(spark, sf_dir):
    """Weight and vector sum of a direct summary are those of the input, coordinate by coordinate."""
    return _sums(stage(summaries.direct_summary(grid(spark, sf_dir).repartition(8), k=5, factor=20), "summary"))


@query(f"WITH {DIM} SELECT count(*) // 64 AS w, CAST(sum(v * v) AS BIGINT) AS ss, true AS small FROM dim")
def direct_summary_invariants(spark, sf_dir):
    s = stage(summaries.direct_summary(grid(spark, sf_dir).repartition(8), k=5, factor=20), "summary")
    return measures.conservation(s).select(F.col("weight").alias("w"), long(F.col("ss")).alias("ss"), (F.col("size") <= 100).alias("small"))


@query("SELECT CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS w, true AS sums_kept, true AS small FROM lineitem")
def weighted_summary_invariants(spark, sf_dir):
    pts = stage(points.quantity_weighted(spark, sf_dir), "points")
    s = stage(summaries.direct_summary(pts, k=5, factor=40, weight_col="w"), "summary")
    want = pts.agg(F.sum(F.col("w") * F.col("x")[0]), F.sum(F.col("w") * F.col("x")[2])).first()
    got = s.agg(F.sum("w").alias("w"), F.sum(F.col("w") * F.col("x")[0]).alias("a"), F.sum(F.col("w") * F.col("x")[2]).alias("b"), F.count("*").alias("m"))
    near = lambda c, v: F.abs(F.col(c) - v) <= 1e-9 * abs(v)
    return got.select("w", (near("a", want[0]) & near("b", want[1])).alias("sums_kept"), (F.col("m") <= 200).alias("small"))


@query("SELECT mode, svd, count(*) AS w, true AS energy_not_above, true AS small FROM embeddings CROSS JOIN (VALUES ('single', 'random'), ('sharded', 'random'), ('sharded', 'exact'), ('sharded', 'gram'), ('sharded', 'random2'), ('sharded', 'none')) v(mode, svd) GROUP BY mode, svd")
def piecewise_summary_invariants(spark, sf_dir):
    e = points.emb64(spark, sf_dir)
    total = e.agg(F.sum(squared_length("x"))).first()[0]
    out = None
    for mode, svd in (("single", "random"), ("sharded", "random"), ("sharded", "exact"), ("sharded", "gram"), ("sharded", "random2"), ("sharded", "none")):
        s = summaries.piecewise_summary(e, 5, ps=100, l=8, svd=svd, mode=mode, factor=20)
        r = measures.conservation(s).select(F.lit(mode).alias("mode"), F.lit(svd).alias("svd"), F.col("weight").alias("w"), (F.col("ss") <= total * (1 + 1e-9)).alias("energy_not_above"), (F.col("size") <= 100).alias("small"))
        out = r if out is None else out.unionByName(r)
    return out


@query("WITH n AS (SELECT count(*) AS n FROM embeddings) SELECT CAST(l.level AS INTEGER) AS level, l.nodes, n.n AS w, true AS small FROM n CROSS JOIN (WITH RECURSIVE t(level, nodes) AS (SELECT 0, CAST(ceil(ceil(count(*) / 50.0) / 3) AS BIGINT) FROM embeddings UNION ALL SELECT level + 1, CAST(ceil(nodes / 3.0) AS BIGINT) FROM t WHERE nodes > 1) SELECT * FROM t) l")
def tree_summary_invariants(spark, sf_dir):
    full = summaries.tree_full(points.emb64(spark, sf_dir), TreeParams(l=8, ps=50, np=3), keep_levels=True)
    per = full.groupBy("level", "node").agg(F.sum("w").alias("w"), F.count("*").alias("m"))
    return per.groupBy("level").agg(F.count("*").alias("nodes"), F.sum("w").alias("w"), (F.max("m") <= 50).alias("small"))


@query("SELECT 45 AS w, 12 AS svds, 4 AS runs, true AS five_rows")
def tree_illustration(spark, sf_dir):
    """Piece size 5, three pieces a node, the first 45 vectors: nine pieces, three nodes, one root of five points."""
    e = points.emb64(spark, sf_dir).filter("id < 45")
    params = TreeParams(l=2, ps=5, np=3)
    full = stage(summaries.tree_full(e, params, keep_levels=True), "illustration")
    counted = summaries.node_counters(full).agg(F.sum("svds").cast("int").alias("svds"), F.count("*").cast("int").alias("runs"))
    return full.filter("level = 1").agg(F.sum("w").cast("int").alias("w"), (F.count("*") <= 5).alias("five_rows")).crossJoin(counted)


@query("SELECT count(*) AS w, true AS small, CAST(ceil(log2(ceil(count(*) / 50.0))) AS INTEGER) AS depth FROM embeddings")
def merge_reduce_invariants(spark, sf_dir):
    s = stage(summaries.merge_reduce(points.emb64(spark, sf_dir), 5, ps=50), "summary")
    return s.agg(F.sum("w").alias("w"), (F.count("*") <= 50).alias("small"), F.max("level").cast("int").alias("depth"))


@query("SELECT flush, levels, count(*) AS w FROM embeddings CROSS JOIN (VALUES ('promote', 'all'), ('merge', 'all'), ('promote', 'leaf'), ('promote', 'none')) v(flush, levels) GROUP BY flush, levels")
def tree_variants(spark, sf_dir):
    """Both rules for half-filled nodes, and projection on all levels, leaves only, or none."""
    e, out = points.emb64(spark, sf_dir), None
    for flush, levels in (("promote", "all"), ("merge", "all"), ("promote", "leaf"), ("promote", "none")):
        s = summaries.tree_summary(e, 5, l=8, ps=60, np=3, flush=flush, project_levels=levels)
        r = s.agg(F.sum("w").alias("w")).select(F.lit(flush).alias("flush"), F.lit(levels).alias("levels"), "w")
        out = r if out is None else out.unionByName(r)
    return out


@query("SELECT 20 AS panels, 20 AS held")
def certificate_panel(spark, sf_dir):
    """Roots of the costs on input and root summary differ by at most the certified error, for every set of the panel."""
    e = points.emb64(spark, sf_dir)
    full = stage(summaries.tree_full(e, TreeParams(l=16, ps=60, np=3), keep_levels=True), "levels")
    top = full.agg(F.max("level")).first()[0]
    bound = summaries.total_error(full)
    dev = measures.coreset_deviation(e, full.filter(F.col("level") == top), measures.center_panel(e, 5))
    ok = F.abs(F.sqrt("input_cost") - F.sqrt("summary_cost")) <= bound * (1 + 1e-9)
    return dev.agg(F.count("*").cast("int").alias("panels"), F.sum(ok.cast("int")).cast("int").alias("held"))


@query("SELECT method, count(*) AS w FROM embeddings CROSS JOIN (VALUES ('cf_tree'), ('sampling_coreset'), ('chain'), ('coupled_tree'), ('running_subspace'), ('uniform_sample')) v(method) GROUP BY method")
def baseline_weights(spark, sf_dir):
    """Every one-pass baseline keeps the total weight."""
    e = points.emb64(spark, sf_dir)
    made = {
        "cf_tree": baselines.cf_tree(e, 5, m=80), "sampling_coreset": baselines.sampling_coreset_summary(e, 5, m=60, ps=100), "chain": baselines.chain_reduce(e, 5, 100, m=80),
        "coupled_tree": baselines.coupled_tree(e, 5, 8, 100), "running_subspace": baselines.running_subspace(e, 5, 8, 100, m=80), "uniform_sample": baselines.uniform_sample(e, 60),
    }
    out = None
    for name, s in made.items():
        r = s.agg(F.sum("w").alias("w")).select(F.lit(name).alias("method"), "w")
        out = r if out is None else out.unionByName(r)
    return out


@query("SELECT method, true AS below_one_center FROM (VALUES ('direct'), ('piecewise'), ('tree'), ('sampling_coreset'), ('uniform_sample')) v(method)")
def method_quality(spark, sf_dir):
    """Centers from every summary cost less on the full input than its centroid does (sampled ones: median of five seeds)."""
    e = points.emb64(spark, sf_dir)
    total = features.cf_agg(e).select(features.cf_within(F.col("cf")).alias("c")).first()["c"]
    made = {
        "direct": [summaries.direct_summary(e, 5, factor=20)], "piecewise": [summaries.piecewise_summary(e, 5, ps=100, l=8, factor=20)], "tree": [summaries.tree_summary(e, 5, l=8, ps=100)],
        "sampling_coreset": [baselines.sampling_coreset_summary(e, 5, m=100, ps=200, seed=seed) for seed in range(5)], "uniform_sample": [baselines.uniform_sample(e, 100, seed) for seed in range(1, 6)],
    }
    rows = []
    for name, made_of in made.items():
        costs = sorted(cost.cost_value(e, clustering.center_rows(clustering.kmeanspp_summary(s, 5, restarts=3))) for s in made_of)
        rows.append((name, costs[len(costs) // 2] <= total))
    return spark.createDataFrame(rows, "method string, below_one_center boolean")


@query("SELECT true AS projected_below_one_center, true AS global_below_one_center")
def two_pass_baselines(spark, sf_dir):
    e = points.emb64(spark, sf_dir)
    total = features.cf_agg(e).select(features.cf_within(F.col("cf")).alias("c")).first()["c"]
    a, _ = baselines.project_then_cluster(e, 4, 6, 125)
    b, _ = baselines.global_projection(e, 4, 6)
    return spark.createDataFrame([(cost.cost_value(e, a) <= total, cost.cost_value(e, b) <= total)], "projected_below_one_center boolean, global_below_one_center boolean")


@query("SELECT seeding, 5 AS runs, true AS below_one_center, true AS near_on_input FROM (VALUES ('d2'), ('uniform')) v(seeding)")
def seeding_on_summary(spark, sf_dir):
    """Five restarts of each seeding on a summary: best cost below one center's there, and near it on the input."""
    e = points.emb64(spark, sf_dir)
    s = stage(summaries.direct_summary(e, 5, factor=20), "summary")
    one = features.cf_agg(s).select(features.cf_within(F.col("cf")).alias("c")).first()["c"]
    lost = s.agg(F.sum("ss_within")).first()[0]
    rows = []
    for how in ("d2", "uniform"):
        runs = stage(clustering.kmeanspp_runs(s, 5, 5, how=how), "runs")
        best = runs.orderBy("cost", "run").first()
        on_input = cost.cost_value(e, list(enumerate(best["centers"])))
        # the input costs what the summary costs and what joining lost, less where points change their center
        rows.append((how, runs.count(), best["cost"] < one, 0.9 * (best["cost"] + lost) <= on_input <= (best["cost"] + lost) * (1 + 1e-9)))
    return spark.createDataFrame(rows, "seeding string, runs int, below_one_center boolean, near_on_input boolean")


@query("SELECT true AS projection_lowers_rank, true AS more_pieces_more_rank")
def intrinsic_growth(spark, sf_dir):
    """Every piece may add its own directions to what one summarizer holds."""
    e = points.emb64(spark, sf_dir)
    one = measures.intrinsic_dim(linalg.project(pieces.by_key(e, 1 << 40), 6, kind="exact"))
    many = measures.intrinsic_dim(linalg.project(pieces.by_key(e, 100), 6, kind="exact"))
    return spark.createDataFrame([(one == 6, many > one)], "projection_lowers_rank boolean, more_pieces_more_rank boolean")


@query("SELECT true AS naive_not_below, true AS exact_merges_more")
def naive_against_exact(spark, sf_dir):
    """The naive increase overestimates: with it a tree of the same threshold holds no fewer features."""
    import numpy as np

    from kmfold.operators.sphere import SphereTree

    e = points.emb64(spark, sf_dir)
    sizes, d = [], points.dimension(e)
    for naive in (True, False):
        t = SphereTree(60, d, 0, block=1, naive=naive)
        for x in matrices(e):
            t.offer(x, (np.arange(len(x)) % 7 + 1))
        sizes.append(t.limit)
    g = np.random.default_rng(0).random((50, 3))
    low = all(a * b / (a + b) * c <= b * c for a, b, c in g)
    return spark.createDataFrame([(low, sizes[1] <= sizes[0])], "naive_not_below boolean, exact_merges_more boolean")


@query("SELECT finder, block, count(*) AS w FROM embeddings CROSS JOIN (VALUES ('full', 1), ('band', 1), ('auto', 1024)) v(finder, block) GROUP BY finder, block")
def insertion_variants(spark, sf_dir):
    out = None
    for finder, block in (("full", 1), ("band", 1), ("auto", 1024)):
        s = summaries.direct_summary(points.emb64(spark, sf_dir), 5, factor=10, finder=finder, block=block)
        r = s.agg(F.sum("w").alias("w")).select(F.lit(finder).alias("finder"), F.lit(block).alias("block"), "w")
        out = r if out is None else out.unionByName(r)
    return out


@query("""SELECT family, n, d, k, CASE WHEN d <= 100 OR k >= d THEN 'direct' WHEN n <= 1000000 THEN 'piecewise' ELSE 'tree' END AS method
FROM (SELECT 'embeddings' AS family, count(*) AS n, CAST(max(len(embedding)) AS INTEGER) AS d FROM embeddings UNION ALL SELECT 'lines', count(*), 128 FROM lineitem UNION ALL SELECT 'events', count(*), 12 FROM events) t
CROSS JOIN (VALUES (10), (1000)) v(k)""")
def method_advice(spark, sf_dir):
    """The method for each point table by its rows, its dimension and k."""
    e = points.emb64(spark, sf_dir)
    sizes = {
        "embeddings": (e.count(), points.dimension(e)), "lines": (points.line_points(spark, sf_dir, 128, dense=False).count(), len(points.line_vectors(128))),
        "events": (points.event_points(spark, sf_dir).count(), points.dimension(points.event_points(spark, sf_dir).limit(1))),
    }
    rows = [(name, n, d, k, summaries.choose(n, d, k)) for name, (n, d) in sizes.items() for k in (10, 1000)]
    return spark.createDataFrame(rows, "family string, n bigint, d int, k int, method string")


@query("SELECT count(*) AS n, 10000 AS summary_rows, CAST(80000 * max(len(embedding)) AS INTEGER) AS piece_bytes, true AS refused FROM embeddings")
def memory_guard(spark, sf_dir):
    """What a task would hold for the table at hand, and a plan refused that does not fit."""
    pts = points.emb64(spark, sf_dir)
    n, d = pts.count(), points.dimension(pts)
    told = measures.memory_model(50, d, 10000, n, 10)
    try:
        measures.check_memory(1000, k=50, d=d, ps=10000, n=n, b=10)
        refused = False
    except ValueError:
        refused = True
    return spark.createDataFrame([(n, 200 * 50, told["piece_bytes"], refused)], "n bigint, summary_rows int, piece_bytes int, refused boolean")


# --- generated workloads ------------------------------------------------------------------------


@query("SELECT k, count(*) AS n, (count(*) - count(DISTINCT o_orderkey % k)) * 5000.0::DOUBLE AS optimum, optimum AS cost_at_truth FROM orders CROSS JOIN (VALUES (5), (10), (50)) v(k) GROUP BY k")
def nested_simplex_optimum(spark, sf_dir):
    """Every order a vertex of the simplex of its key's class: cost at the true centers, through the sparse rows, against the closed form."""
    ids = points.table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("id"))
    rows = None
    for k in (5, 10, 50):
        s = generators.simplex_rows(ids, k, sparse=True)
        flat = s.select("label", F.explode(F.arrays_zip("pos", "val")).alias("z")).select("label", F.col("z.pos").alias("p"), F.col("z.val").alias("v"))
        dims = flat.groupBy("label", "p").agg(F.count("*").alias("m"), F.sum("v").alias("ls"), F.sum(F.col("v") * F.col("v")).alias("ss"))
        # the coordinate of a class has a row for each of its points and cancels out; the others are summed apart from it, so nothing is lost
        left, own = F.col("ss") - F.col("ls") * F.col("ls") / F.col("m"), F.col("p") >= k
        rest = F.sum(F.when(own, F.col("ss"))) - F.sum(F.when(own, F.col("ls") * F.col("ls"))) / F.max("m")
        by = dims.groupBy("label").agg(F.max("m").alias("m"), (rest + F.sum(F.when(~own, left))).alias("c"))
        one = by.agg(F.sum("m").alias("n"), F.count("*").alias("classes"), F.sum("c").alias("c"))
        leg = F.lit(generators.INNER**2 / 2)
        one = one.select(F.lit(k).alias("k"), "n", ((F.col("n") - F.col("classes")) * leg).alias("optimum"), F.round("c", 3).alias("cost_at_truth"))
        rows = one if rows is None else rows.unionByName(one)
    return rows


@query("SELECT 10 AS clusters, true AS optimum_reached")
def nested_simplex_recovered(spark, sf_dir):
    pts = generators.nested_simplex(spark, 10, 500)
    s = stage(summaries.tree_summary(pts, 10, l=20, ps=100, np=3), "summary")
    centers = clustering.center_rows(clustering.kmeanspp_summary(s, 10, restarts=5))
    got = cost.cost_value(pts, centers)
    return spark.createDataFrame([(len(centers), got <= 1.05 * generators.simplex_optimum(10, 500))], "clusters int, optimum_reached boolean")


def _value_sql(key: str, seed: int, half: str) -> str:
    return f"(({_hash(key, seed)} / 2147483647.0) * 2.0 - 1.0) * {half}"


@query(f"SELECT CAST(round(sum(v * v)) AS BIGINT) AS cost FROM (SELECT {_value_sql('i.range * 64 + j.range', 3, '10.0')} AS v FROM range(1000) i CROSS JOIN range(64) j)")
def uniform_cube_onecenter(spark, sf_dir):
    return generators.uniform_cube(spark, 1000, 64).agg(long(F.sum(squared_length("x"))).alias("cost"))


@query("SELECT l_returnflag || l_linestatus AS block, CAST(sum(l_quantity * l_quantity + round(l_extendedprice / 1000) * round(l_extendedprice / 1000) + round(l_discount * 100) * round(l_discount * 100) + round(l_tax * 100) * round(l_tax * 100) + 353) AS BIGINT) AS cost FROM lineitem GROUP BY 1")
def block_signal_onecenter(spark, sf_dir):
    """Blocks of lineitem rows in 32 coordinates, each with signal (10) in those of its own flag and status: cost of the origin.

    The one-hot coordinates add 100 + 100 + 25 + 64 + 64 to every row.
    """
    sq = sum(F.round(v) * F.round(v) for v in points.line_vectors(32))
    pts = points.table(spark, sf_dir, "lineitem").select(F.concat("l_returnflag", "l_linestatus").alias("block"), sq.cast("bigint").alias("sq"))
    return pts.groupBy("block").agg(F.sum("sq").alias("cost"))


@query("SELECT count(*) AS n, true AS block_near, true AS cube_near FROM lineitem")
def one_center_expectations(spark, sf_dir):
    """Quantities, part keys and order keys are even over their ranges: as a cube, and as blocks (by line number) with signal in one of them."""
    line = points.table(spark, sf_dir, "lineitem")
    names = ("l_quantity", "l_partkey", "l_orderkey")
    ends = line.agg(*[f(c).alias(f"{c}_{f.__name__}") for c in names for f in (F.min, F.max)])
    # one row of ranges
    spread = [((F.col(c) - F.col(f"{c}_min") + 0.5) / (F.col(f"{c}_max") - F.col(f"{c}_min") + 1) * 2 - 1).alias(c) for c in names]
    x = line.crossJoin(F.broadcast(ends)).select(F.pmod("l_linenumber", F.lit(3)).alias("block"), *spread)
    half = [F.when(F.col("block") == j, generators.SIGNAL).otherwise(generators.NOISE) for j in range(3)]
    cube, block = (sum(F.col(c) * F.col(c) * h * h for c, h in zip(names, scale)) for scale in ([generators.SIGNAL] * 3, half))
    told = x.agg(F.count("*").alias("n"), F.sum(cube).alias("cube"), F.sum(block).alias("block")).first()
    a, b = told["block"] / generators.one_center_cost_block(told["n"], 3, 1), told["cube"] / generators.one_center_cost_cube(told["n"], 3)
    return spark.createDataFrame([(told["n"], abs(a - 1) < 0.02, abs(b - 1) < 0.02)], "n bigint, block_near boolean, cube_near boolean")


@query("SELECT family, true AS energy_rises FROM (VALUES ('embeddings'), ('documents'), ('blocks'), ('simplex'), ('cube'), ('words')) v(family)")
def spectra_of_families(spark, sf_dir):
    """Share of energy in the first ten directions by family: skewed for words and simplices, flat for the cube."""
    made = {
        "embeddings": points.emb64(spark, sf_dir), "documents": points.bag_of_words(points.table(spark, sf_dir, "documents"), "doc_id", 64), "blocks": generators.block_signal(spark, 10, 50, 64, x=16),
        "simplex": generators.nested_simplex(spark, 5, 100), "cube": generators.uniform_cube(spark, 500, 64), "words": generators.words(spark, 500, 64),
    }
    rows = []
    for name, pts in made.items():
        s = [r["energy_cum"] for r in linalg.spectrum(pts).orderBy("rank").collect()]
        rows.append((name, all(a <= b + 1e-9 for a, b in zip(s, s[1:])) and abs(s[-1] - 1) < 1e-6))
    return spark.createDataFrame(rows, "family string, energy_rises boolean")


@query("WITH t AS (SELECT doc_id AS id, unnest(string_split_regex(lower(coalesce(text, '')), '[^a-z0-9]+')) AS token FROM documents) SELECT substr(token, 1, 1) AS first, count(DISTINCT token) AS tokens, count(*) AS n FROM t WHERE token <> '' GROUP BY 1")
def doc_term_counts(spark, sf_dir):
    t = points.tokens(points.table(spark, sf_dir, "documents"), "doc_id")
    return t.groupBy(F.substring("token", 1, 1).alias("first")).agg(F.countDistinct("token").alias("tokens"), F.sum("n").alias("n"))


@query("WITH t AS (SELECT doc_id AS id, unnest(string_split_regex(lower(coalesce(text, '')), '[^a-z0-9]+')) AS token FROM documents), h AS (SELECT id, CAST('0x' || substr(md5(token), 1, 7) AS BIGINT) % 256 AS b FROM t WHERE token <> ''), c AS (SELECT id, b, count(*) AS n FROM h GROUP BY id, b) SELECT b AS bucket, CAST(sum(n) AS BIGINT) AS total, CAST(sum(n * n) AS BIGINT) AS squares FROM c GROUP BY b")
def doc_hashed_vectors(spark, sf_dir):
    v = points.bag_of_words(points.table(spark, sf_dir, "documents"), "doc_id", 256)
    flat = v.select(F.posexplode("x").alias("b", "n")).filter("n > 0")
    return flat.groupBy(F.col("b").cast("bigint").alias("bucket")).agg(F.sum("n").cast("bigint").alias("total"), F.sum(F.col("n") * F.col("n")).cast("bigint").alias("squares"))


@query("SELECT k, count(*) AS w FROM documents CROSS JOIN (VALUES (2), (4), (10)) v(k) GROUP BY k")
def words_workload(spark, sf_dir):
    """Bag of words through the piecewise method, k in 2, 4, 10."""
    v, out = stage(points.bag_of_words(points.table(spark, sf_dir, "documents"), "doc_id", 256), "words"), None
    for k in (2, 4, 10):
        s = summaries.piecewise_summary(v, k, ps=250, l=linalg.target_dim(k), factor=20)
        r = s.agg(F.sum("w").alias("w")).select(F.lit(k).alias("k"), "w")
        out = r if out is None else out.unionByName(r)
    return out


@query("SELECT count(*) AS w, true AS centers FROM events")
def evolving_stream(spark, sf_dir):
    """Events in time order through the tree: neighbours in time share a node."""
    s = stage(summaries.tree_summary(points.event_points(spark, sf_dir), 5, l=6, ps=200, np=5), "summary")
    c = clustering.kmeanspp_summary(s, 5, restarts=2)
    return s.agg(F.sum("w").alias("w")).crossJoin(c.agg((F.count("*") == 5).alias("centers")))


@query("SELECT count(*) AS w, true AS close FROM lineitem")
def long_stream(spark, sf_dir):
    """Many rows of 32 coordinates: the direct summary's centers cost near k-means++ on the full table."""
    pts = stage(points.line_points(spark, sf_dir, 32), "points")
    s = stage(summaries.direct_summary(pts, 5, factor=40), "summary")
    a = cost.cost_value(pts, clustering.center_rows(clustering.kmeanspp_summary(s, 5, restarts=3)))
    _, b = clustering.kmeanspp(pts, 5, max_iter=6)
    return s.agg(F.sum("w").alias("w"), F.lit(a <= 1.1 * b[-1]).alias("close"))


# --- run tables -----------------------------------------------------------------------------------


def run_values() -> list[tuple]:
    rows = []
    for i, (method, k, l) in enumerate((m, k, l) for m in ("direct", "piecewise", "tree") for k in (10, 50) for l in (15, 75)):  # noqa: E741
        for seed in range(5):
            rows.append((method, k, l, seed, float(1000 + (i * 37 + seed * 13) % 101), float(10 + (i * 7 + seed * 5) % 29)))
    return rows


RUN = "runs(method, k, l, seed, cost, seconds) AS (VALUES " + ", ".join(f"('{m}', {k}, {l}, {s}, {c}::DOUBLE, {t}::DOUBLE)" for m, k, l, s, c, t in run_values()) + ")"


def run_table(spark) -> DataFrame:
    return spark.createDataFrame(run_values(), "method string, k int, l int, seed int, cost double, seconds double")


@query(f"WITH {RUN} SELECT method, k, min(cost) AS cost_min, max(cost) AS cost_max, avg(cost) AS cost_avg, median(cost) AS cost_median, min(seconds) AS seconds_min, max(seconds) AS seconds_max, avg(seconds) AS seconds_avg, median(seconds) AS seconds_median FROM runs GROUP BY method, k")
def run_stats(spark, sf_dir):
    return measures.run_statistics(run_table(spark), ["method", "k"])


@query(f"WITH {RUN}, m AS (SELECT method, k, l, median(cost) AS c, median(seconds) AS s FROM runs GROUP BY ALL) SELECT a.method, a.k, a.l, a.c / b.c AS cost_ratio, b.s / a.s AS speedup FROM m a JOIN m b ON b.method = 'direct' AND a.k = b.k AND a.l = b.l")
def speed_and_quality_ratios(spark, sf_dir):
    return measures.ratios(run_table(spark), "direct", ["k", "l"])


@query("WITH c AS (SELECT l_returnflag AS flag, l_linenumber AS line, (l_quantity - 25) * (l_quantity - 25) + (round(l_discount * 100) - 5) * (round(l_discount * 100) - 5) + (round(l_tax * 100) - 4) * (round(l_tax * 100) - 4) AS cost FROM lineitem) SELECT coalesce(flag, 'all') AS flag, coalesce(CAST(line AS VARCHAR), 'all') AS line, grouping_id(flag, line) AS g, count(*) AS n, median(cost) AS cost FROM c GROUP BY CUBE (flag, line)")
def cost_cube(spark, sf_dir):
    """Median cost of a lineitem row to a fixed center, by flag, by line number, by both and over all; costs are whole numbers with few values."""
    near = [F.col("l_quantity") - 25, F.round(F.col("l_discount") * 100) - 5, F.round(F.col("l_tax") * 100) - 4]
    rows = points.table(spark, sf_dir, "lineitem").select(F.col("l_returnflag").alias("flag"), F.col("l_linenumber").alias("line"), (near[0] * near[0] + near[1] * near[1] + near[2] * near[2]).alias("cost"))
    few = rows.groupBy("flag", "line", "cost").agg(F.count("*").alias("m"))
    c = few.cube("flag", "line").agg(F.grouping_id("flag", "line").alias("g"), F.sum("m").alias("n"), F.percentile("cost", 0.5, F.col("m")).alias("cost"))
    return c.select(F.coalesce("flag", F.lit("all")).alias("flag"), F.coalesce(F.col("line").cast("string"), F.lit("all")).alias("line"), "g", "n", "cost")


@query("SELECT 'tree' AS method, 5 AS runs, true AS timed, count(*) AS points FROM embeddings")
def repeated_runs(spark, sf_dir):
    """Five seeds through the run table: cost on the full input and driver seconds."""
    e = points.emb64(spark, sf_dir)

    def once(seed):
        s = summaries.tree_summary(e, 5, l=8, ps=100, seed=seed)
        return cost.cost_value(e, clustering.center_rows(clustering.kmeanspp_summary(s, 5, restarts=2, seed=seed))), {"k": 5}

    runs = measures.repeat(spark, "tree", {"k": 5, "l": 8}, range(5), once)
    return runs.groupBy("method").agg(F.count("*").cast("int").alias("runs"), F.every(F.col("seconds") > 0).alias("timed")).crossJoin(e.agg(F.count("*").alias("points")))


@query("SELECT CAST(level AS INTEGER) AS level, true AS counted FROM (WITH RECURSIVE t(level, nodes) AS (SELECT 0, CAST(ceil(ceil(count(*) / 50.0) / 3) AS BIGINT) FROM embeddings UNION ALL SELECT level + 1, CAST(ceil(nodes / 3.0) AS BIGINT) FROM t WHERE nodes > 1) SELECT * FROM t)")
def node_counters(spark, sf_dir):
    full = summaries.tree_full(points.emb64(spark, sf_dir), TreeParams(l=8, ps=50, np=3), keep_levels=True)
    c = summaries.node_counters(full)
    return c.groupBy("level").agg(F.every((F.col("n_out") <= F.col("n_in")) & (F.col("dist_evals") > 0) & (F.col("threshold") >= 0)).alias("counted"))


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Embeddings through the tree (k=5, pieces of 50, 8 dimensions, three pieces a node): centers, weights, cost shares."""
    e = points.emb64(spark, sf_dir)
    s = stage(summaries.tree_summary(e, 5, l=8, ps=50, np=3), "summary")
    centers = clustering.center_rows(clustering.kmeanspp_summary(s, 5))
    near = cost.assign(e, centers, vectorized=True).groupBy("cid").agg(F.sum("w").alias("weight"), F.sum(F.col("w") * F.col("d2")).alias("cost"))
    return near.select("cid", "weight", "cost", (F.col("cost") / F.sum("cost").over(clustering.Window.partitionBy())).alias("cost_share"))
