"""Sources, sinks and relational operators around the methods."""

from __future__ import annotations


import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions import rng, sqlfunctions
from ..operators import ledger as led
from ..operators import mechanisms, scoring
from ..sources import examples
from ..sources.scratch import scratch
from ..sources.tables import load, read_examples, register_views
from ..streaming import streams
from .base import SQL_EMBEDDINGS, SQL_LINEITEM, query, sql_laplace, sql_u

R = (0.5, -1.25, 2.0, 0.25)
_S = "(" + " + ".join(f"x[{i + 1}] * {w}::DOUBLE" for i, w in enumerate(R)) + ")"


def fixed_release() -> mechanisms.Release:
    return mechanisms.Release(np.array(R), 0.1, 1.0, 100, 1.0, 1.0, 2.0, "hinge", "finite", release_id="fixed")


@query("scan_parquet", "SELECT count(*) AS n, round(sum(l_quantity), 2) AS q FROM lineitem")
def scan_parquet(spark, sf_dir):
    return load(spark, sf_dir, "lineitem").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("q"))


def _round_trip(spark, sf_dir, fmt, **options):
    t = load(spark, sf_dir, "supplier").select("s_suppkey", "s_name", "s_acctbal")
    path = scratch(spark)
    t.write.format(fmt).options(**options).save(path)
    return read_examples(spark, path, fmt, t.schema, **options)


for _fmt, _opt in (("csv", {"header": "true"}), ("json", {}), ("orc", {})):
    query(f"scan_{_fmt}_roundtrip", "SELECT s_suppkey, s_name, s_acctbal FROM supplier")(lambda spark, sf_dir, f=_fmt, o=_opt: _round_trip(spark, sf_dir, f, **o))


@query("assemble_lineitem", f"SELECT row_id, round(x[2], 9) AS price, y FROM {SQL_LINEITEM}")
def assemble_lineitem(spark, sf_dir):
    return examples.lineitem(spark, sf_dir).select("row_id", F.round(F.get("x", F.lit(1)), 9).alias("price"), "y")


_ORDERS = """SELECT o_orderkey AS row_id, round(greatest(0.0::DOUBLE, least(1.0::DOUBLE, o_totalprice / 500000)), 9) AS price, round(greatest(0.0::DOUBLE, least(1.0::DOUBLE, (c_acctbal + 1000) / 11000)), 9) AS bal, n_regionkey AS region,
CASE WHEN substr(o_orderpriority, 1, 1) IN ('1', '2') THEN 1.0::DOUBLE ELSE -1.0::DOUBLE END AS y FROM orders LEFT JOIN customer ON o_custkey = c_custkey LEFT JOIN nation ON c_nationkey = n_nationkey"""


def _orders(spark, sf_dir, hint=None):
    t = examples.orders(spark, sf_dir, hint)
    at = lambda i: F.round(F.get("x", F.lit(i)), 9)
    region = F.array_position(F.slice("x", 8, 5), 1.0) - 1
    return t.select("row_id", at(0).alias("price"), at(1).alias("bal"), region.cast("int").alias("region"), "y")


query("assemble_orders", _ORDERS)(_orders)
query("join_merge", _ORDERS)(lambda spark, sf_dir: _orders(spark, sf_dir, "merge"))
query("join_shuffle_hash", _ORDERS)(lambda spark, sf_dir: _orders(spark, sf_dir, "shuffle_hash"))


@query("join_broadcast", "SELECT doc_id, coalesce(quality, -1) AS quality FROM documents LEFT JOIN labels USING (doc_id)")
def join_broadcast(spark, sf_dir):
    return load(spark, sf_dir, "documents").join(load(spark, sf_dir, "labels"), "doc_id", "left").select("doc_id", F.coalesce("quality", F.lit(-1)).alias("quality"))


@query("filter_public_stratum", "SELECT l_shipdate::DATE AS day, count(*) AS n FROM lineitem WHERE l_shipdate >= TIMESTAMP '1995-01-01' AND l_shipdate < TIMESTAMP '1995-03-01' AND l_returnflag IN ('A', 'R') GROUP BY 1")
def filter_public_stratum(spark, sf_dir):
    """A public stratum: the predicate reaches the scan."""
    t = load(spark, sf_dir, "lineitem").where("l_shipdate >= TIMESTAMP_NTZ '1995-01-01' AND l_shipdate < TIMESTAMP_NTZ '1995-03-01' AND l_returnflag IN ('A', 'R')")
    return t.groupBy(F.to_date("l_shipdate").alias("day")).agg(F.count("*").alias("n"))


@query("pairs_theta", "SELECT a.s_suppkey AS i, count(*) AS n, round(min(b.s_acctbal - a.s_acctbal), 2) AS least FROM supplier a JOIN supplier b ON b.s_acctbal > a.s_acctbal AND b.s_acctbal - a.s_acctbal <= 500 AND a.s_nationkey <> b.s_nationkey GROUP BY 1")
def pairs_theta(spark, sf_dir):
    """Suppliers of other nations with up to 500 more on their account: an inequality join, by bands that make it an equality join of neighbours."""
    s = load(spark, sf_dir, "supplier").select("s_suppkey", F.col("s_acctbal").cast("double").alias("bal"), "s_nationkey").withColumn("band", F.floor(F.col("bal") / 500))
    a = s.select(F.col("s_suppkey").alias("i"), F.col("bal").alias("ba"), F.col("s_nationkey").alias("na"), F.explode(F.array("band", F.col("band") + 1)).alias("band"))
    b = s.select(F.col("bal").alias("bb"), F.col("s_nationkey").alias("nb"), "band")
    near = a.join(b, "band").where((F.col("bb") > F.col("ba")) & (F.col("bb") - F.col("ba") <= 500) & (F.col("na") != F.col("nb")))
    return near.groupBy("i").agg(F.count("*").alias("n"), F.round(F.min(F.col("bb") - F.col("ba")), 2).alias("least"))


#: Releases of the registry for joins over time: (id, first day, last day exclusive), by public day numbers of the event stream.
_REG = [("r1", 0, 10), ("r2", 10, 20), ("r3", 20, 400)]
_REG_SQL = "(VALUES " + ", ".join(f"('{a}', {b}, {c})" for a, b, c in _REG) + ") AS g(release_id, lo, hi)"
_DAY = "(epoch(ts) / 86400)::DOUBLE - (SELECT min(floor(epoch(ts) / 86400)) FROM events)"


def _days(spark, sf_dir):
    e = load(spark, sf_dir, "events").select("event_id", (F.unix_micros(F.col("ts").cast("timestamp")) / 86400e6).alias("d"))
    first = F.broadcast(e.agg(F.min(F.floor("d")).alias("first")))
    return e.crossJoin(first).select("event_id", (F.col("d") - F.col("first")).alias("day"))


@query("interval_release", f"SELECT event_id, release_id FROM (SELECT event_id, {_DAY} AS day FROM events) JOIN {_REG_SQL} ON day >= lo AND day < hi")
def interval_release(spark, sf_dir):
    reg = spark.createDataFrame(_REG, "release_id string, lo int, hi int")
    return _days(spark, sf_dir).join(F.broadcast(reg), (F.col("day") >= F.col("lo")) & (F.col("day") < F.col("hi"))).select("event_id", "release_id")


@query("asof_release", f"SELECT event_id, max_by(release_id, lo) AS release_id FROM (SELECT event_id, {_DAY} AS day FROM events) JOIN {_REG_SQL} ON lo <= day GROUP BY 1")
def asof_release(spark, sf_dir):
    """The latest release before each event: an array of the small registry's starts is searched in place, without a shuffle."""
    starts = F.array(*[F.struct(F.lit(b).alias("lo"), F.lit(a).alias("id")) for a, b, _ in _REG])
    last = F.array_max(F.filter(starts, lambda s: s["lo"] <= F.col("day")))
    return _days(spark, sf_dir).select("event_id", last["id"].alias("release_id"))


@query("semi_labels", "SELECT doc_id FROM documents WHERE doc_id IN (SELECT doc_id FROM labels)")
def semi_labels(spark, sf_dir):
    return load(spark, sf_dir, "documents").select("doc_id").join(load(spark, sf_dir, "labels"), "doc_id", "left_semi")


@query("anti_labels", "SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
def anti_labels(spark, sf_dir):
    return load(spark, sf_dir, "documents").select("doc_id").join(load(spark, sf_dir, "labels"), "doc_id", "left_anti")


@query("full_hist", "SELECT coalesce(a.k, b.k) AS k, coalesce(a.n, 0) AS orders, coalesce(b.n, 0) AS customers FROM (SELECT o_custkey % 7 AS k, count(*) AS n FROM orders GROUP BY 1) a FULL JOIN (SELECT c_custkey % 5 AS k, count(*) AS n FROM customer GROUP BY 1) b ON a.k = b.k")
def full_hist(spark, sf_dir):
    a = load(spark, sf_dir, "orders").groupBy((F.col("o_custkey") % 7).alias("k")).agg(F.count("*").alias("orders"))
    b = load(spark, sf_dir, "customer").groupBy((F.col("c_custkey") % 5).alias("k")).agg(F.count("*").alias("customers"))
    return a.join(b, "k", "full").fillna(0)


@query("weights_array", "SELECT p - 1 AS pos, w[p] AS value FROM (SELECT [0.5, -1.25, 2.0, 0.25]::DOUBLE[] AS w), range(1, 5) AS t(p)")
def weights_array(spark, sf_dir):
    """Long weights to an ordered array and back."""
    long = spark.createDataFrame([(3, 0.25), (1, -1.25), (0, 0.5), (2, 2.0)], "pos long, w double")
    arr = long.agg(F.array_sort(F.collect_list(F.struct("pos", "w"))).alias("a")).select(F.transform("a", lambda s: s["w"]).alias("w"))
    return arr.select(F.posexplode("w").alias("pos", "value")).select(F.col("pos").cast("long").alias("pos"), "value")


@query("distinct_counts", "SELECT count(DISTINCT user_id) AS users, count(DISTINCT event_type) AS kinds, true AS approx_close FROM events")
def distinct_counts(spark, sf_dir):
    e = load(spark, sf_dir, "events")
    n = F.count_distinct("user_id")
    return e.agg(n.alias("users"), F.count_distinct("event_type").alias("kinds"), (F.abs(F.approx_count_distinct("user_id") - n) <= 0.15 * n).alias("approx_close"))


_CELL = "count(*) AS n, sum(l_linenumber)::BIGINT AS s"


def _cells(g):
    return g.agg(F.count("*").alias("n"), F.sum("l_linenumber").alias("s"))


@query("contingency_cube", f"SELECT l_returnflag, l_linestatus, {_CELL} FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
def contingency_cube(spark, sf_dir):
    return _cells(load(spark, sf_dir, "lineitem").cube("l_returnflag", "l_linestatus"))


@query("contingency_rollup", f"SELECT l_returnflag, l_linestatus, {_CELL} FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)")
def contingency_rollup(spark, sf_dir):
    return _cells(load(spark, sf_dir, "lineitem").rollup("l_returnflag", "l_linestatus"))


@query("contingency_sets", f"SELECT l_returnflag, l_linestatus, {_CELL} FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus))")
def contingency_sets(spark, sf_dir):
    register_views(spark, sf_dir)
    return spark.sql("SELECT l_returnflag, l_linestatus, count(*) AS n, sum(l_linenumber) AS s FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus))")


@query("sweep_pivot", "SELECT l_linestatus, sum(CASE WHEN l_returnflag = 'A' THEN 1 ELSE 0 END)::BIGINT AS A, sum(CASE WHEN l_returnflag = 'N' THEN 1 ELSE 0 END)::BIGINT AS N, sum(CASE WHEN l_returnflag = 'R' THEN 1 ELSE 0 END)::BIGINT AS R FROM lineitem GROUP BY 1")
def sweep_pivot(spark, sf_dir):
    return load(spark, sf_dir, "lineitem").groupBy("l_linestatus").pivot("l_returnflag", ["A", "N", "R"]).count()


@query("win_prefix", "SELECT o_custkey, o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderkey ROWS UNBOUNDED PRECEDING) AS nth FROM orders")
def win_prefix(spark, sf_dir):
    w = Window.partitionBy("o_custkey").orderBy("o_orderkey").rowsBetween(Window.unboundedPreceding, 0)
    return load(spark, sf_dir, "orders").select("o_custkey", "o_orderkey", F.count("*").over(w).alias("nth"))


@query("win_cap", "SELECT event_id, user_id FROM (SELECT event_id, user_id, row_number() OVER (PARTITION BY user_id ORDER BY event_id) AS r FROM events) WHERE r <= 3")
def win_cap(spark, sf_dir):
    """A bound on each user's rows before training: group privacy then costs its factor."""
    w = Window.partitionBy("user_id").orderBy("event_id")
    return load(spark, sf_dir, "events").select("event_id", "user_id", F.row_number().over(w).alias("r")).where("r <= 3").drop("r")


@query("win_lag", "SELECT o_custkey, o_orderkey, o_orderkey - lag(o_orderkey) OVER w AS step, lead(o_orderkey) OVER w AS next FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderkey)")
def win_lag(spark, sf_dir):
    w = Window.partitionBy("o_custkey").orderBy("o_orderkey")
    return load(spark, sf_dir, "orders").select("o_custkey", "o_orderkey", (F.col("o_orderkey") - F.lag("o_orderkey").over(w)).alias("step"), F.lead("o_orderkey").over(w).alias("next"))


@query("win_ntile", "SELECT s_nationkey, s_suppkey, ntile(3) OVER (PARTITION BY s_nationkey ORDER BY s_suppkey)::INTEGER AS fold FROM supplier")
def win_ntile(spark, sf_dir):
    w = Window.partitionBy("s_nationkey").orderBy("s_suppkey")
    return load(spark, sf_dir, "supplier").select("s_nationkey", "s_suppkey", F.ntile(3).over(w).alias("fold"))


_LEDGER = [("a", "s1", "r1", 0.5, 1), ("a", "s1", "r2", 0.25, 2), ("a", "s2", "r3", 0.75, 3), ("a", "s1", "r4", 0.5, 4), ("a", "s1", "r6", 0.25, 6), ("b", "s1", "r5", 1.5, 5)]
_LED_SQL = "(VALUES " + ", ".join(f"('{a}', '{b}', '{c}', {d}::DOUBLE, {e})" for a, b, c, d, e in _LEDGER) + ") AS t(dataset, stratum, release_id, beta, ts)"


def _ledger(spark) -> DataFrame:
    return spark.createDataFrame(_LEDGER, "dataset string, stratum string, release_id string, beta double, ts int")


@query("win_ledger", f"""WITH RECURSIVE r AS (SELECT *, row_number() OVER (PARTITION BY dataset, stratum ORDER BY ts, release_id) AS k FROM {_LED_SQL}),
g AS (SELECT *, CASE WHEN beta <= 1 THEN beta ELSE 0.0::DOUBLE END AS spent, beta <= 1 AS granted FROM r WHERE k = 1
UNION ALL SELECT r.*, g.spent + CASE WHEN g.spent + r.beta <= 1 THEN r.beta ELSE 0.0::DOUBLE END, g.spent + r.beta <= 1 FROM g JOIN r ON r.dataset = g.dataset AND r.stratum = g.stratum AND r.k = g.k + 1)
SELECT dataset, stratum, release_id, beta, ts, spent, granted FROM g""")
def win_ledger(spark, sf_dir):
    return led.balance(_ledger(spark), 1.0)


query("ledger_sequential", f"SELECT dataset, sum(beta) AS beta FROM {_LED_SQL} GROUP BY 1")(lambda spark, sf_dir: led.sequential(_ledger(spark)))
query("ledger_parallel", f"SELECT dataset, max(b) AS beta FROM (SELECT dataset, stratum, sum(beta) AS b FROM {_LED_SQL} GROUP BY 1, 2) GROUP BY 1")(lambda spark, sf_dir: led.parallel(_ledger(spark)))


@query("registry_roundtrip", "SELECT 'lineitem' AS dataset, 'fixed' AS release_id, p - 1 AS pos, w[p] AS value FROM (SELECT [0.5, -1.25, 2.0, 0.25]::DOUBLE[] AS w), range(1, 5) AS t(p)")
def registry_roundtrip(spark, sf_dir):
    path = scratch(spark)
    led.register(fixed_release().frame(spark), path, "lineitem")
    r = spark.read.parquet(path).where("dataset = 'lineitem'")
    return r.select("dataset", "release_id", F.posexplode("w").alias("pos", "value")).withColumn("pos", F.col("pos").cast("long"))


@query("release_json", "SELECT 'fixed' AS release_id, 4::BIGINT AS weights, false AS leaks")
def release_json(spark, sf_dir):
    j = led.export_json(fixed_release().frame(spark))
    leak = F.lower("json").rlike("alpha|support|noise_seed|w_true|accuracy")
    return j.select(F.get_json_object("json", "$.release_id").alias("release_id"), F.size(F.from_json(F.get_json_object("json", "$.w"), "array<double>")).cast("long").alias("weights"), leak.alias("leaks"))


@query("topk_weights", "SELECT pos::BIGINT AS pos, w FROM (VALUES (0, 0.5::DOUBLE), (1, -1.25), (2, 2.0), (3, 0.25)) AS t(pos, w) ORDER BY abs(w) DESC LIMIT 2")
def topk_weights(spark, sf_dir):
    return fixed_release().frame(spark).select(F.posexplode("w").alias("pos", "w")).select(F.col("pos").cast("long").alias("pos"), "w").orderBy(F.desc(F.abs("w"))).limit(2)


@query("event_hours", "SELECT event_id, hour(ts)::INTEGER AS h, date_trunc('day', ts)::DATE AS day, epoch(ts)::BIGINT AS secs FROM events")
def event_hours(spark, sf_dir):
    t = F.col("ts").cast("timestamp")
    return load(spark, sf_dir, "events").select("event_id", F.hour(t).alias("h"), F.to_date(F.date_trunc("day", t)).alias("day"), F.rint(F.unix_micros(t) / 1e6).cast("long").alias("secs"))


@query("json_props", "SELECT event_id, (props::JSON ->> 'k')::BIGINT AS k FROM events")
def json_props(spark, sf_dir):
    return load(spark, sf_dir, "events").select("event_id", F.from_json("props", "k long")["k"].alias("k"))


@query("map_wordcount", "SELECT item_id, w, count(*) AS n FROM (SELECT item_id, unnest(regexp_split_to_array(lower(text), '[ \n]+')) AS w FROM benchmark) WHERE w <> '' GROUP BY 1, 2")
def map_wordcount(spark, sf_dir):
    """Word counts as one map a row, and unfolded again."""
    w = load(spark, sf_dir, "benchmark").select("item_id", F.explode(F.split(F.lower("text"), "[ \n]+")).alias("w")).where("w <> ''").groupBy("item_id", "w").agg(F.count("*").alias("n"))
    m = w.groupBy("item_id").agg(F.map_from_entries(F.collect_list(F.struct("w", "n"))).alias("m"))
    return m.select("item_id", F.explode("m").alias("w", "n"))


_BUCKET = "CAST('0x' || substr(md5('split:' || CAST(o_orderkey AS VARCHAR)), 1, 8) AS BIGINT) % 10"


def _bucket(key: str):
    return F.conv(F.substring(F.md5(F.concat(F.lit("split:"), F.col(key).cast("string")).cast("binary")), 1, 8), 16, 10).cast("long") % 10


@query("split_hash", f"SELECT {_BUCKET} AS bucket, count(*) AS n FROM orders GROUP BY 1")
def split_hash(spark, sf_dir):
    return load(spark, sf_dir, "orders").groupBy(_bucket("o_orderkey").alias("bucket")).agg(F.count("*").alias("n"))


@query("fixed_sample", "SELECT o_orderkey FROM orders ORDER BY md5('s' || CAST(o_orderkey AS VARCHAR)) LIMIT 100")
def fixed_sample(spark, sf_dir):
    return load(spark, sf_dir, "orders").orderBy(F.md5(F.concat(F.lit("s"), F.col("o_orderkey").cast("string")).cast("binary"))).limit(100).select("o_orderkey")


@query("sql_release_features", f"WITH c AS (SELECT count(*) AS n FROM lineitem) SELECT l_returnflag, round(sum(l_quantity / 50) / (SELECT n FROM c), 9) AS share FROM lineitem GROUP BY 1")
def sql_release_features(spark, sf_dir):
    register_views(spark, sf_dir)
    return spark.sql("WITH c AS (SELECT count(*) AS n FROM lineitem) SELECT l_returnflag, round(sum(l_quantity / 50) / (SELECT n FROM c), 9) AS share FROM lineitem GROUP BY 1")


@query("udf_score", f"SELECT row_id, round({_S}, 9) + 0.0 AS score FROM {SQL_LINEITEM}")
def udf_score(spark, sf_dir):
    """The released classifier as an SQL function."""
    sqlfunctions.register_all(spark)
    examples.lineitem(spark, sf_dir).createOrReplaceTempView("dpm_rows")
    w = ", ".join(f"{x}D" for x in R)
    return spark.sql(f"SELECT row_id, round(dpm_dot(x, array({w})), 9) + 0.0D AS score FROM dpm_rows")


@query("score_release", f"SELECT row_id, round({_S}, 9) + 0.0 AS score FROM {SQL_LINEITEM}")
def score_release(spark, sf_dir):
    return scoring.score(examples.lineitem(spark, sf_dir), fixed_release()).select("row_id", (F.round("score", 9) + 0.0).alias("score"))


@query("udaf_vector_sum", f"SELECT p - 1 AS pos, round(sum(y * x[p]), 6) + 0.0 AS s FROM {SQL_EMBEDDINGS}, range(1, 65) AS t(p) GROUP BY p")
def udaf_vector_sum(spark, sf_dir):
    """The Arrow sum pass that solvers use."""
    from ..operators.passes import sum_pass

    s = sum_pass(examples.embeddings(spark, sf_dir), 64, lambda x, y, k: (k * y) @ x)
    return spark.createDataFrame([(i, float(round(a, 6)) + 0.0) for i, a in enumerate(s)], "pos long, s double")


@query("udtf_noise", f"SELECT i AS pos, round({sql_laplace(sql_u(7, 'lap', 'i'), '0.5')}, 9) AS mu FROM range(32) AS t(i)")
def udtf_noise(spark, sf_dir):
    sqlfunctions.register_all(spark)
    return spark.sql("SELECT pos, round(mu, 9) AS mu FROM dpm_noise(32, 0.5D, 7)")


@query("udtf_packing", "SELECT db::BIGINT AS db, round(cos(2 * pi() * db / 6), 9) + 0.0 AS x1, round(sin(2 * pi() * db / 6), 9) + 0.0 AS x2 FROM range(6) AS t(db)")
def udtf_packing(spark, sf_dir):
    sqlfunctions.register_all(spark)
    return spark.sql("SELECT db, round(x1, 9) + 0.0D AS x1, round(x2, 9) + 0.0D AS x2 FROM dpm_packing(0.5D)")


# --- streams, each with its batch twin in SQL -------------------------------------------------------------------------


def _run(spark, stream, mode="append"):
    return streams.run_to_table(stream, scratch(spark), mode)


_X = "greatest(0.0::DOUBLE, least(1.0::DOUBLE, value / 100.0::DOUBLE))"


@query("stream_score", f"SELECT event_id, round({_X} * 2.0::DOUBLE, 9) AS score FROM events")
def stream_score(spark, sf_dir):
    s = streams.score_stream(streams.stream_events(spark, sf_dir), [2.0]).select("event_id", F.round("score", 9).alias("score"))
    return _run(spark, s)


def _windows(kind, **options):
    def run(spark, sf_dir):
        e = streams.score_stream(streams.stream_events(spark, sf_dir), [1.0]).withColumn("score", F.col("score") - 0.5)
        t = streams.windows(e, kind, options.get("size", ""), options.get("slide"), options.get("gap"), watermark=None)
        return _run(spark, t.withColumn("start", F.unix_timestamp("start")).withColumn("positives", F.col("positives").cast("long")), "complete")

    return run


_EV = f"(SELECT user_id, epoch(ts) AS t, CASE WHEN {_X} - 0.5 >= 0 THEN 1 ELSE 0 END AS pos FROM events)"
query("stream_tumbling", f"SELECT (floor((t - 0) / 604800) * 604800)::BIGINT AS start, count(*) AS n, sum(pos)::BIGINT AS positives FROM {_EV} GROUP BY 1")(_windows("tumbling", size="7 days"))
query("stream_sliding", f"SELECT (floor(t / 86400) * 86400 - k * 86400)::BIGINT AS start, count(*) AS n, sum(pos)::BIGINT AS positives FROM {_EV}, range(7) AS r(k) GROUP BY 1")(_windows("sliding", size="7 days", slide="1 day"))
query("stream_session", f"""SELECT user_id, floor(min(t))::BIGINT AS start, count(*) AS n, sum(pos)::BIGINT AS positives FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY t ROWS UNBOUNDED PRECEDING) AS s
FROM (SELECT *, CASE WHEN t - lag(t) OVER (PARTITION BY user_id ORDER BY t) < 21600 THEN 0 ELSE 1 END AS fresh FROM {_EV})) GROUP BY user_id, s""")(_windows("session", gap="6 hours"))


@query("stream_cap", "SELECT user_id, least(count(*), 3) AS n FROM events GROUP BY 1")
def stream_cap(spark, sf_dir):
    s = streams.cap_contributions(streams.stream_events(spark, sf_dir), 3)
    return _run(spark, s).groupBy("user_id").agg(F.count("*").alias("n"))


@query("stream_late", "SELECT count(*) AS n, sum(CASE WHEN ts < seen - INTERVAL 1 DAY THEN 1 ELSE 0 END)::BIGINT AS late FROM (SELECT ts, max(ts) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS seen FROM events)")
def stream_late(spark, sf_dir):
    e = streams.prepared(load(spark, sf_dir, "events"))
    return streams.late_rows(e).agg(F.count("*").alias("n"), F.sum(F.when(F.col("late"), 1).otherwise(0)).alias("late"))


@query("stream_release", "SELECT start, 0.5::DOUBLE AS beta, 1::BIGINT AS weights, false AS exact FROM (SELECT DISTINCT (floor(epoch(ts) / 604800) * 604800)::BIGINT AS start FROM events) WHERE start + 604800 <= (SELECT max(epoch(ts)) - 86400 FROM events)")
def stream_release(spark, sf_dir):
    """One release a closed window, its level debited from a ledger first; the open last window gets none."""
    out, ledger = scratch(spark), scratch(spark)
    streams.release_per_window(streams.stream_events(spark, sf_dir), "7 days", 1, 1.0, 0.5, out, ledger, 0.5, scratch(spark)).awaitTermination()
    r = streams.read_batches(spark, out, streams.RELEASED)
    debits = spark.read.parquet(ledger).select(F.col("stratum").cast("long").alias("start"), F.col("beta").alias("debit"))
    return r.join(debits, "start").select("start", F.col("debit").alias("beta"), F.size("w").cast("long").alias("weights"), (F.col("n") == F.floor("n")).alias("exact"))
