"""Surrounding operators on the tables of tissues: joins, windows, sets, sketches, streams."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import gru, udfs
from ..operators import ghosts, grid, interactions, measures
from ..sources import scenario_source
from ..sources.scratch import scratch
from ..sources.tissues import DEFAULT_CUTOFF, hundredths, order_tissue, table, vector_cloud
from ..streaming import telemetry as streams
from . import sql
from .balance_queries import BOUNDS, IDS, SCENARIO_M, SCENARIO_SQL, SCENARIO_STEPS, static_times
from .balance_queries import ORACLES as BALANCE

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def add(name: str, query, oracle: str | None = None) -> None:
    QUERIES[name] = query
    if oracle:
        ORACLES[name] = oracle


add("join_equi", lambda s, d: table(s, d, "orders").join(table(s, d, "customer"), F.col("o_custkey") == F.col("c_custkey")).groupBy("c_mktsegment").agg(F.count(F.lit(1)).alias("n")), "SELECT c_mktsegment, count(*)::BIGINT AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1")
add("join_semi", lambda s, d: table(s, d, "customer").join(table(s, d, "orders"), F.col("o_custkey") == F.col("c_custkey"), "left_semi").select("c_custkey"), "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")
add(
    "join_anti",
    lambda s, d: (e := vector_cloud(s, d)).join(interactions.binned(e, 3000).select(F.col("cell_id_a").alias("cell_id")), "cell_id", "left_anti").select("cell_id"),
    f"WITH {sql.elements('vector')}, {sql.pair_counts(3000)} SELECT cell_id FROM e WHERE NOT EXISTS (SELECT 1 FROM pairs WHERE pairs.cell_id = e.cell_id)",
)
add("join_outer", lambda s, d: table(s, d, "nation").join(table(s, d, "supplier"), F.col("n_nationkey") == F.col("s_nationkey"), "left").groupBy("n_name").agg(F.count("s_suppkey").alias("n")), "SELECT n_name, count(s_suppkey)::BIGINT AS n FROM nation LEFT JOIN supplier ON n_nationkey = s_nationkey GROUP BY 1")


def range_join(spark: SparkSession, folder: str) -> DataFrame:
    """Pairs of events of like value at most 60 s apart: a band on time as an equality on minutes."""
    e = table(spark, folder, "events").select("event_id", "event_type", F.expr("unix_micros(cast(ts as timestamp)) div 1000000").alias("t"))
    a = e.withColumn("m", F.explode(F.array(*(F.expr(f"t div 60 + {k}") for k in (-1, 0, 1)))))
    b = e.select(F.col("event_id").alias("other"), F.col("event_type").alias("type_b"), F.col("t").alias("t_b"), F.expr("t div 60").alias("m"))
    return a.join(b, "m").where((F.col("event_type") == F.col("type_b")) & (F.abs(F.col("t") - F.col("t_b")) <= 60) & (F.col("event_id") < F.col("other"))).select("event_id", "other")


add("join_range", range_join, "WITH e AS (SELECT event_id, event_type, epoch_us(ts) // 1000000 AS t FROM events) SELECT a.event_id, b.event_id AS other FROM e a JOIN e b ON a.event_type = b.event_type AND abs(a.t - b.t) <= 60 AND a.event_id < b.event_id")


def as_of(spark: SparkSession, folder: str) -> DataFrame:
    """The latest purchase value in force at each click of a user: a union and one window."""
    e = table(spark, folder, "events").select("event_id", "user_id", "ts", "value", "event_type")
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    held = e.withColumn("latest", F.last(F.when(F.col("event_type") == "purchase", F.col("value")), ignorenulls=True).over(w))
    return held.where("event_type = 'click'").select("event_id", "latest")


add("join_as_of", as_of, "SELECT event_id, latest FROM (SELECT event_id, event_type, last_value(CASE WHEN event_type = 'purchase' THEN value END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS latest FROM events) WHERE event_type = 'click'")
add("window_ranking", lambda s, d: table(s, d, "customer").select("c_custkey", F.row_number().over(Window.partitionBy("c_nationkey").orderBy(F.desc("c_acctbal"), "c_custkey")).alias("rn"), F.ntile(4).over(Window.partitionBy("c_nationkey").orderBy("c_custkey")).alias("quarter")), "SELECT c_custkey, row_number() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey)::INTEGER AS rn, ntile(4) OVER (PARTITION BY c_nationkey ORDER BY c_custkey)::INTEGER AS quarter FROM customer")
add("window_frames", lambda s, d: table(s, d, "orders").select("o_orderkey", F.count(F.lit(1)).over(Window.partitionBy("o_custkey").orderBy("o_orderkey").rowsBetween(-3, 0)).alias("trailing"), F.lag("o_orderkey").over(Window.partitionBy("o_custkey").orderBy("o_orderkey")).alias("previous")), "SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderkey ROWS BETWEEN 3 PRECEDING AND CURRENT ROW)::BIGINT AS trailing, lag(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderkey) AS previous FROM orders")
add("group_rollup", lambda s, d: table(s, d, "lineitem").rollup("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n")), "SELECT l_returnflag, l_linestatus, count(*)::BIGINT AS n FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)")
add("group_pivot", lambda s, d: table(s, d, "lineitem").groupBy("l_returnflag").pivot("l_linestatus", ["F", "O"]).agg(F.count(F.lit(1))).select("l_returnflag", F.coalesce("F", F.lit(0)).alias("f"), F.coalesce("O", F.lit(0)).alias("o")), "SELECT l_returnflag, count(*) FILTER (l_linestatus = 'F')::BIGINT AS f, count(*) FILTER (l_linestatus = 'O')::BIGINT AS o FROM lineitem GROUP BY 1")
add("aggregate_distinct", lambda s, d: table(s, d, "lineitem").agg(F.count_distinct("l_partkey").alias("parts"), F.count_if(F.col("l_discount") > 0.05).alias("reduced"), F.max_by("l_orderkey", F.struct("l_extendedprice", "l_orderkey")).alias("dearest")), "SELECT count(DISTINCT l_partkey)::BIGINT AS parts, count(*) FILTER (l_discount > 0.05)::BIGINT AS reduced, (SELECT l_orderkey FROM lineitem ORDER BY l_extendedprice DESC, l_orderkey DESC LIMIT 1) AS dearest FROM lineitem")
add("sketches", lambda s, d: table(s, d, "events").agg(F.approx_count_distinct("user_id", 0.01).alias("users"), F.percentile_approx("value", F.lit(0.99), F.lit(10000)).alias("p99")))
add("top_k", lambda s, d: table(s, d, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(10).select("o_orderkey", "o_totalprice"), "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10")
add("set_operations", lambda s, d: table(s, d, "customer").select(F.col("c_nationkey").alias("k")).intersect(table(s, d, "supplier").select("s_nationkey")).union(table(s, d, "nation").select("n_nationkey").exceptAll(table(s, d, "supplier").select("s_nationkey"))).distinct(), "SELECT c_nationkey AS k FROM customer INTERSECT SELECT s_nationkey FROM supplier UNION SELECT n_nationkey FROM (SELECT n_nationkey FROM nation EXCEPT SELECT s_nationkey FROM supplier)")
add("json_and_dates", lambda s, d: table(s, d, "events").select("event_id", F.get_json_object("props", "$.k").cast("int").alias("k"), F.hour("ts").alias("hour"), F.date_format("ts", "yyyy-MM-dd").alias("day")).groupBy("day", "hour").agg(F.sum("k").cast("bigint").alias("k")), "SELECT strftime(ts, '%Y-%m-%d') AS day, hour(ts)::INTEGER AS hour, sum(CAST(json_extract_string(props, '$.k') AS INTEGER))::BIGINT AS k FROM events GROUP BY ALL")
add("strings_urls", lambda s, d: table(s, d, "pages").groupBy(F.regexp_extract("url", "^https?://([^/]+)", 1).alias("host")).agg(F.count(F.lit(1)).alias("n")), "SELECT regexp_extract(url, '^https?://([^/]+)', 1) AS host, count(*)::BIGINT AS n FROM pages GROUP BY 1")
add("sample_by_hash", lambda s, d: table(s, d, "orders").where((F.col("o_orderkey") * 48271 + 11) % 2147483647 % 10 == 0).select("o_orderkey"), "SELECT o_orderkey FROM orders WHERE (o_orderkey * 48271 + 11) % 2147483647 % 10 = 0")


def lineage_depth(spark: SparkSession, folder: str) -> DataFrame:
    """Ancestors of every cell of a binary lineage, by a recursive query."""
    edges = table(spark, folder, "nation").select(F.col("n_nationkey").alias("id"), F.expr("(n_nationkey - 1) div 2").alias("parent")).where("id > 0")
    return spark.sql("WITH RECURSIVE up(id, ancestor, depth) AS (SELECT id, parent, 1 FROM {edges} UNION ALL SELECT u.id, e.parent, u.depth + 1 FROM up u JOIN {edges} e ON e.id = u.ancestor) SELECT cast(id as bigint) AS id, cast(max(depth) as int) AS depth FROM up GROUP BY id", edges=edges)


add("lineage_depth", lineage_depth, "WITH RECURSIVE e AS (SELECT n_nationkey AS id, (n_nationkey - 1) // 2 AS parent FROM nation WHERE n_nationkey > 0), up(id, ancestor, depth) AS (SELECT id, parent, 1 FROM e UNION ALL SELECT u.id, e.parent, u.depth + 1 FROM up u JOIN e ON e.id = u.ancestor) SELECT id::BIGINT AS id, max(depth)::INTEGER AS depth FROM up GROUP BY id")


def lateral_top(spark: SparkSession, folder: str) -> DataFrame:
    """The two dearest customers of each nation, from a lateral subquery."""
    n, c = table(spark, folder, "nation").alias("n"), table(spark, folder, "customer")
    own = c.where(F.col("c_nationkey") == F.col("n.n_nationkey").outer()).orderBy(F.desc("c_acctbal"), "c_custkey").limit(2)
    return n.lateralJoin(own).select("n_name", "c_custkey")


add("join_lateral", lateral_top, "SELECT n_name, c_custkey FROM (SELECT n_name, c_custkey, row_number() OVER (PARTITION BY n_nationkey ORDER BY c_acctbal DESC, c_custkey) AS rn FROM nation JOIN customer ON c_nationkey = n_nationkey) WHERE rn <= 2")


def analytic(spark: SparkSession, folder: str) -> DataFrame:
    w = Window.partitionBy("o_custkey").orderBy("o_orderkey")
    whole = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    columns = {"second": F.nth_value("o_orderkey", 2).over(whole), "first": F.first("o_orderkey").over(whole), "next": F.lead("o_orderkey").over(w), "share": F.round(F.percent_rank().over(w), 6), "upto": F.round(F.cume_dist().over(w), 6)}
    return table(spark, folder, "orders").select("o_orderkey", *(c.alias(n) for n, c in columns.items()))


add(
    "window_analytic",
    analytic,
    "SELECT o_orderkey, nth_value(o_orderkey, 2) OVER a AS second, first_value(o_orderkey) OVER a AS first, lead(o_orderkey) OVER w AS next, round(percent_rank() OVER w, 6) AS share, round(cume_dist() OVER w, 6) AS upto FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderkey), a AS (PARTITION BY o_custkey ORDER BY o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)",
)
add("window_range", lambda s, d: table(s, d, "events").select("event_id", F.count(F.lit(1)).over(Window.partitionBy("event_type").orderBy(F.expr("unix_micros(cast(ts as timestamp))")).rangeBetween(-3_600_000_000, 0)).alias("last_hour")), "SELECT event_id, count(*) OVER (PARTITION BY event_type ORDER BY epoch_us(ts) RANGE BETWEEN 3600000000 PRECEDING AND CURRENT ROW)::BIGINT AS last_hour FROM events")
add(
    "aggregate_statistics",
    lambda s, d: table(s, d, "lineitem").groupBy("l_returnflag").agg(F.round(F.stddev("l_quantity"), 6).alias("deviation"), F.round(F.regr_slope("l_extendedprice", "l_quantity"), 4).alias("slope"), F.expr("count(*) filter (where l_discount > 0.05)").alias("reduced"), F.expr("percentile(l_quantity, 0.5)").alias("median"), F.sort_array(F.collect_set("l_linestatus")).cast("string").alias("states")),
    "SELECT l_returnflag, round(stddev(l_quantity), 6) AS deviation, round(regr_slope(l_extendedprice, l_quantity), 4) AS slope, count(*) FILTER (l_discount > 0.05)::BIGINT AS reduced, quantile_cont(l_quantity, 0.5) AS median, '[' || string_agg(DISTINCT l_linestatus, ', ' ORDER BY l_linestatus) || ']' AS states FROM lineitem GROUP BY 1",
)
add(
    "variant_props",
    lambda s, d: table(s, d, "events").select(F.parse_json("props").alias("v"), "event_type").groupBy("event_type").agg(F.sum(F.variant_get("v", "$.k", "bigint")).cast("bigint").alias("k"), F.max(F.expr("map_from_arrays(array('k'), array(variant_get(v, '$.k', 'int')))['k']")).alias("most")),
    "SELECT event_type, sum(CAST(json_extract_string(props, '$.k') AS BIGINT))::BIGINT AS k, max(CAST(json_extract_string(props, '$.k') AS INTEGER)) AS most FROM events GROUP BY 1",
)


def sketches_within_bounds(spark: SparkSession, folder: str) -> DataFrame:
    """Exact answers, and whether sketches of bounded size come near them."""
    e = table(spark, folder, "events")
    row = e.agg(
        F.count_distinct("user_id").alias("users"), F.hll_sketch_estimate(F.hll_sketch_agg("user_id", F.lit(14))).alias("hll"), F.approx_count_distinct("user_id", 0.01).alias("acd"), F.count_if(F.col("user_id") == 1).alias("one"),
        F.expr("percentile(value, 0.9)").alias("p90"), F.expr("kll_sketch_get_quantile_double(kll_sketch_agg_double(value), 0.9D)").alias("kll"), F.percentile_approx("value", 0.9, 10000).alias("gk"), F.count(F.lit(1)).alias("n"),
    )
    near = lambda a, b, part: F.abs(F.col(a) - F.col(b)) <= F.greatest(part * F.col(b), F.lit(1.0))
    return row.select("users", "one", near("hll", "users", 0.05).alias("hll_near"), near("acd", "users", 0.05).alias("acd_near"), near("kll", "p90", 0.1).alias("kll_near"), near("gk", "p90", 0.1).alias("gk_near"))


add("sketches_within_bounds", sketches_within_bounds, "SELECT count(DISTINCT user_id)::BIGINT AS users, count(*) FILTER (user_id = 1)::BIGINT AS one, true AS hll_near, true AS acd_near, true AS kll_near, true AS gk_near FROM events")


def formats(spark: SparkSession, folder: str) -> DataFrame:
    """Nations written to and read from each file format."""
    nation, base, out = table(spark, folder, "nation"), scratch(spark, f"formats-{uuid.uuid4().hex}"), None
    for kind in ("parquet", "csv", "json", "orc"):
        nation.write.format(kind).save(f"{base}/{kind}")
        part = spark.read.schema(nation.schema).format(kind).load(f"{base}/{kind}").select(F.lit(kind).alias("format"), "n_nationkey", "n_name")
        out = part if out is None else out.unionByName(part)
    return out


add("formats_round_trip", formats, "SELECT format, n_nationkey, n_name FROM nation, (VALUES ('parquet'), ('csv'), ('json'), ('orc')) t(format)")


def slab_sink(spark: SparkSession, folder: str) -> DataFrame:
    """Owned elements written by rank; a reader of one rank opens that folder alone."""
    path = scratch(spark, f"slabs-{uuid.uuid4().hex}")
    placed = ghosts.attach(order_tissue(spark, folder), [0.0, 600_000.0], DEFAULT_CUTOFF["order"])
    ghosts.assemble(placed.withColumn("slab", F.col("home_rank"))).write.partitionBy("slab").parquet(path)
    return spark.read.parquet(path).where("slab = 1").agg(F.count(F.lit(1)).alias("n"), F.sum("x").cast("bigint").alias("x"))


add("slab_sink", slab_sink, f"WITH {sql.elements('order')} SELECT count(*)::BIGINT AS n, sum(x)::BIGINT AS x FROM e WHERE x >= 0 AND x < 600000")


def scenario_read(spark: SparkSession, folder: str) -> DataFrame:
    scenario_source.register(spark)
    return spark.read.format("scenario_loads").options(ids=str(IDS), steps=str(SCENARIO_STEPS), m=str(SCENARIO_M)).load()


add("scenario_source", scenario_read, SCENARIO_SQL)

SERIES, EVENTS = 8, 20


WINDOW_US = 30 * 86_400_000_000 // EVENTS


def recorded_inputs(spark: SparkSession, folder: str) -> DataFrame:
    """series, xs: recorded inputs of the controller, from whole numbers: values of events by group of users, window of time and feature."""
    when = F.expr(f"(unix_micros(cast(ts as timestamp)) - 1704067200000000) div {WINDOW_US}")
    seen = table(spark, folder, "events").groupBy((F.col("user_id") % SERIES).alias("series"), when.alias("t"), (F.col("event_id") % 12).alias("f")).agg(F.sum(hundredths("value")).alias("w"))
    held = seen.groupBy("series", "t").agg(F.map_from_entries(F.collect_list(F.struct("f", "w"))).alias("at"))
    x = F.transform(F.sequence(F.lit(0).cast("bigint"), F.lit(11).cast("bigint")), lambda f: (F.coalesce(F.element_at("at", f), F.lit(0)) % 2001 - 1000) / F.lit(1000.0))
    every = spark.range(SERIES * EVENTS).select(F.expr(f"id div {EVENTS}").alias("series"), (F.col("id") % EVENTS).alias("t"))
    rows = every.join(F.broadcast(held), ["series", "t"], "left").select("series", "t", x.alias("x"))
    return rows.groupBy("series").agg(F.transform(F.sort_array(F.collect_list(F.struct("t", "x"))), lambda r: r["x"]).alias("xs"))


def residual_rows(found: DataFrame) -> DataFrame:
    return found.select("series", F.posexplode("r").alias("t", "residual")).select("series", "t", (F.round("residual", 6) + 0.0).alias("residual"))


def _gates(v: str, weights, bias, size: int) -> str:
    flat, own = [[", ".join(f"{float(x)!r}::DOUBLE" for x in a)] for a in (weights.T.ravel(), bias)]
    return f"list_transform(range(0, {3 * gru.HIDDEN}), lambda j: ([{own[0]}])[j + 1] + list_sum(list_transform(range(1, {size + 1}), lambda i: {v}[i] * ([{flat[0]}])[j * {size} + i])))"


def _residual_sql(w: gru.Weights) -> str:
    n = gru.HIDDEN
    u = f"(1 / (1 + exp(-(a[k + {n}] + z[k + {n}]))))"
    state = f"list_transform(range(1, {n + 1}), lambda k: (1 - {u}) * tanh(a[k + {2 * n}] + z[k + {2 * n}] / (1 + exp(-(a[k] + z[k])))) + {u} * h[k])"
    head = ", ".join(f"{float(x)!r}::DOUBLE" for x in w["head"][:, 0])
    return f"""WITH RECURSIVE seen AS (SELECT user_id % {SERIES} AS series, (epoch_us(ts) - 1704067200000000) // {WINDOW_US} AS t, event_id % 12 AS f, sum(CAST(round(value * 100) AS BIGINT))::BIGINT AS w FROM events GROUP BY ALL),
x AS (SELECT series, t, list((coalesce(w, 0) % 2001 - 1000) / 1000.0::DOUBLE ORDER BY f) AS x FROM range({SERIES}) a(series) CROSS JOIN range({EVENTS}) b(t) CROSS JOIN range(12) c(f) LEFT JOIN seen USING (series, t, f) GROUP BY series, t),
s(series, t, h) AS (SELECT i, 0::BIGINT, list_transform(range(0, {n}), lambda k: 0::DOUBLE) FROM range({SERIES}) q(i) UNION ALL
  SELECT series, t + 1, {state} FROM (SELECT series, t, h, {_gates('x', w['w_x'], w['b_x'], 12)} AS a, {_gates('h', w['w_h'], w['b_h'], n)} AS z FROM s JOIN x USING (series, t)))
SELECT series, (t - 1)::INTEGER AS t, round({float(w['bias'][0])!r}::DOUBLE + list_sum(list_transform(range(1, {n + 1}), lambda i: h[i] * ([{head}])[i])), 6) + 0.0 AS residual FROM s WHERE t > 0"""


#: Export parity: the shipped weights give the same residuals in numpy, in Spark's SQL and in another engine's.
_PARITY = _residual_sql(gru.trained())
add("parity_numpy", lambda s, d: residual_rows(recorded_inputs(s, d).withColumn("r", udfs.gru_residual(gru.trained())("xs"))), _PARITY)
add("parity_sql", lambda s, d: residual_rows(recorded_inputs(s, d).withColumn("r", udfs.sql_residuals(gru.trained(), "xs"))), _PARITY)

add("udf_imbalance", lambda s, d: static_times(s, d).groupBy("step").agg(F.round(udfs.imbalance()("t"), 6).alias("i_global")), f"SELECT step, i_global FROM ({BALANCE['imbalance_static']})")


def udtf_stencil(spark: SparkSession, folder: str) -> DataFrame:
    """Elements around each occupied bin of the vector tissue, through the table function."""
    udfs.register(spark)
    bins = grid.bins(vector_cloud(spark, folder), 10000)
    return spark.sql("SELECT s.bx, s.by, s.bz, sum(b.n) AS n_near FROM {bins} b, LATERAL stencil(b.bx, b.by, b.bz) s GROUP BY s.bx, s.by, s.bz", bins=bins)


add("udtf_stencil", udtf_stencil, f"WITH {sql.elements('vector')}, {sql.binned(10000)}, {sql.bins()}, {sql.SHIFTS}, {sql.AROUND} SELECT bx, by_ AS by, bz, n_near FROM around")


def sql_function_proposals(spark: SparkSession, folder: str) -> DataFrame:
    """The reactive rule as a SQL function."""
    udfs.register(spark)
    pairs, widths = measures.local_imbalance(static_times(spark, folder)), ", ".join(f"{b - a}D" for a, b in zip(BOUNDS, BOUNDS[1:], strict=False))
    return spark.sql(f"SELECT step, boundary, round(reactive_proposal(t_left, t_right, array({widths})[boundary - 1], array({widths})[boundary], 0.02D, 0.5D), 6) AS proposal FROM {{pairs}}", pairs=pairs)


add("sql_function_proposals", sql_function_proposals, BALANCE["reactive_proposals"])


def telemetry(spark: SparkSession, folder: str) -> DataFrame:
    """Events as rank times of two runs."""
    return table(spark, folder, "events").select(F.concat(F.lit("run"), F.col("user_id") % 2).alias("run_id"), (F.col("event_id") % 1000).cast("int").alias("step"), (F.col("user_id") % 8).cast("int").alias("rank"), F.col("ts").cast("timestamp").alias("ts"), F.col("value").alias("t_obs"))


def streamed(spark: SparkSession, folder: str, make, mode: str = "complete") -> DataFrame:
    """What make() gives for the telemetry as a file stream, run to its end."""
    name = f"telemetry_{uuid.uuid4().hex}"
    base = scratch(spark, name)
    telemetry(spark, folder).orderBy("ts").coalesce(1).write.parquet(f"{base}/in")
    stream = spark.readStream.schema(streams.TELEMETRY).parquet(f"{base}/in")
    q = make(stream).writeStream.outputMode(mode).format("memory").queryName(name).option("checkpointLocation", f"{base}/state").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.table(name)


def stream_equals_batch(spark: SparkSession, folder: str) -> DataFrame:
    """Windowed imbalance from a stream; equal to the batch SQL."""
    out = streamed(spark, folder, lambda s: streams.windowed_imbalance(s, 8, "10 minutes", "1 day"))
    return out.select("run_id", F.date_format("start", "yyyy-MM-dd").alias("day"), "n", F.round("i_global", 6).alias("i_global"))


_TELEMETRY = "e AS (SELECT 'run' || (user_id % 2) AS run_id, (event_id % 1000)::INTEGER AS step, user_id % 8 AS rank, ts, value FROM events)"
add(
    "stream_telemetry_batch_equal",
    stream_equals_batch,
    f"WITH {_TELEMETRY}, r AS (SELECT run_id, strftime(ts, '%Y-%m-%d') AS day, rank, sum(value) AS t, count(*) AS n FROM e GROUP BY ALL) SELECT run_id, day, sum(n)::BIGINT AS n, round((max(t) - min(t)) / avg(t), 6) AS i_global FROM r GROUP BY ALL",
)
add(
    "stream_sliding",
    lambda s, d: streamed(s, d, lambda x: streams.windowed_imbalance(x, 8, "10 minutes", "2 days", "1 day")).groupBy("run_id").agg(F.count(F.lit(1)).alias("windows"), F.sum("n").alias("n")),
    f"WITH {_TELEMETRY}, w AS (SELECT run_id, CAST(ts AS DATE) - i::INTEGER AS day FROM e, range(2) q(i)) SELECT run_id, count(DISTINCT day)::BIGINT AS windows, count(*)::BIGINT AS n FROM w GROUP BY 1",
)
add(
    "stream_sessions",
    lambda s, d: streamed(s, d, lambda x: streams.sessions(x, "30 minutes")).groupBy("run_id").agg(F.count(F.lit(1)).alias("sessions"), F.max("n").alias("longest"), F.sum("n").alias("n")),
    f"""WITH {_TELEMETRY}, g AS (SELECT run_id, ts, (lag(ts) OVER (PARTITION BY run_id ORDER BY ts) + INTERVAL 30 MINUTE > ts)::INTEGER AS near FROM e),
s AS (SELECT run_id, sum(1 - coalesce(near, 0)) OVER (PARTITION BY run_id ORDER BY ts) AS k FROM g), c AS (SELECT run_id, k, count(*) AS n FROM s GROUP BY ALL)
SELECT run_id, count(*)::BIGINT AS sessions, max(n)::BIGINT AS longest, sum(n)::BIGINT AS n FROM c GROUP BY 1""",
)
add("stream_once", lambda s, d: streamed(s, d, lambda x: streams.reported_once(x, "60 days"), "append").groupBy("run_id").agg(F.count(F.lit(1)).alias("n")), f"WITH {_TELEMETRY} SELECT run_id, count(DISTINCT (step, rank))::BIGINT AS n FROM e GROUP BY 1")


def stream_static_join(spark: SparkSession, folder: str) -> DataFrame:
    """Telemetry joined, as it comes, with a table of the ranks' slices."""
    widths = spark.createDataFrame([(r, b - a) for r, (a, b) in enumerate(zip(BOUNDS, BOUNDS[1:], strict=False))], "rank int, width int")
    return streamed(spark, folder, lambda x: x.join(F.broadcast(widths), "rank").groupBy("rank", "width").agg(F.count(F.lit(1)).alias("n")))


add("stream_static_join", stream_static_join, f"WITH {_TELEMETRY} SELECT rank::INTEGER AS rank, ([{', '.join(str(b - a) for a, b in zip(BOUNDS, BOUNDS[1:], strict=False))}])[rank + 1]::INTEGER AS width, count(*)::BIGINT AS n FROM e GROUP BY 1, 2")
