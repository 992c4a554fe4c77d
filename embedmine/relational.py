"""Operators that a user needs around mining, each with its SQL: scans, joins, aggregates, windows, sets, scalars, streams."""

from __future__ import annotations

from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .apps import motifs
from .queries import plain
from .sources import formats
from .sources.derived import copart, custsupp, table
from .streaming import windows

Query = Callable[[SparkSession, str], DataFrame]
_queries: dict[str, Query] = {}
_sql: dict[str, str] = {}


def op(sql: str | None):
    def mark(f: Query) -> Query:
        def run(spark: SparkSession, sf_dir: str) -> DataFrame:
            return plain(f(spark, sf_dir))

        run.__name__, run.__doc__ = f.__name__, f.__doc__
        _queries[f.__name__] = run
        if sql:
            _sql[f.__name__] = sql
        return f

    return mark


@op("SELECT c_custkey, c_name FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders WHERE o_totalprice > 200000)")
def op_semi(s, d):
    big = table(s, d, "orders").where("o_totalprice > 200000")
    return table(s, d, "customer").join(big, F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey", "c_name")


@op("SELECT c_custkey, c_name FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders WHERE o_totalprice > 300000)")
def op_anti(s, d):
    return table(s, d, "customer").join(table(s, d, "orders").where("o_totalprice > 300000"), F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey", "c_name")


@op("SELECT coalesce(n_name, '') AS n_name, coalesce(s_name, '') AS s_name FROM nation FULL JOIN (SELECT * FROM supplier WHERE s_acctbal > 5000) ON n_nationkey = s_nationkey")
def op_outer(s, d):
    rich = table(s, d, "supplier").where("s_acctbal > 5000")
    return table(s, d, "nation").join(rich, F.col("n_nationkey") == F.col("s_nationkey"), "full").select(F.coalesce("n_name", F.lit("")).alias("n_name"), F.coalesce("s_name", F.lit("")).alias("s_name"))


@op("SELECT n_regionkey, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_regionkey")
def op_broadcast_join(s, d):
    """The nation table has 25 rows at every scale."""
    return table(s, d, "customer").join(F.broadcast(table(s, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_regionkey").agg(F.count(F.lit(1)).alias("n"))


@op("SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND b.event_type = 'purchase' AND a.event_type = 'click' AND b.ts >= a.ts AND b.ts < a.ts + INTERVAL 30 MINUTE")
def op_range_join(s, d):
    """Purchases within half an hour after a click of the same user, by time bins."""
    e = table(s, d, "events").select("event_id", "user_id", "event_type", "ts", windows.micros("ts").alias("t"))
    width = 30 * 60_000_000
    left = e.where("event_type = 'click'").select(F.col("event_id").alias("a"), "user_id", F.col("t").alias("ta"), F.explode(F.array(F.floor(F.col("t") / width), F.floor(F.col("t") / width) + 1)).alias("bin"))
    right = e.where("event_type = 'purchase'").select(F.col("event_id").alias("b"), "user_id", F.col("t").alias("tb"), F.floor(F.col("t") / width).alias("bin"))
    return left.join(right, ["user_id", "bin"]).where(f"tb >= ta and tb < ta + {width}").select("a", "b")


@op("SELECT o_orderkey, coalesce((SELECT max(event_id) FROM events e WHERE e.user_id = o.o_custkey AND e.ts = (SELECT max(ts) FROM events x WHERE x.user_id = o.o_custkey AND x.ts <= o.d)), -1) AS event_id FROM (SELECT o_orderkey, o_custkey, DATE '2024-01-01' + INTERVAL (o_orderkey % 31) DAY AS d FROM orders) o")
def op_asof(s, d):
    """The last event of the customer before a day: both sides in one window, the last event carried on."""
    day = F.expr("TIMESTAMP_NTZ '2024-01-01 00:00:00' + make_dt_interval(cast(o_orderkey % 31 as int))")
    o = table(s, d, "orders").select(F.col("o_custkey").alias("k"), windows.micros(day).alias("t"), F.lit(1).alias("side"), "o_orderkey", F.lit(None).cast("long").alias("event_id"))
    e = table(s, d, "events").select(F.col("user_id").alias("k"), windows.micros("ts").alias("t"), F.lit(0).alias("side"), F.lit(None).cast("long").alias("o_orderkey"), "event_id")
    w = Window.partitionBy("k").orderBy("t", "side", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    return o.unionByName(e).withColumn("event_id", F.last("event_id", True).over(w)).where("side = 1").select("o_orderkey", F.coalesce("event_id", F.lit(-1)).alias("event_id"))


@op("SELECT a.r_name AS a, b.n_name AS b FROM region a CROSS JOIN nation b")
def op_cross_toy(s, d):
    """Two dictionaries of 5 and 25 rows."""
    return table(s, d, "region").select(F.col("r_name").alias("a")).crossJoin(table(s, d, "nation").select(F.col("n_name").alias("b")))


_GROUPED = "SELECT coalesce(p_type, '*') AS p_type, coalesce(p_brand, '*') AS p_brand, count(*) AS n, max(p_size) AS most FROM part GROUP BY "


@op(_GROUPED + "CUBE (p_type, p_brand)")
def op_cube(s, d):
    return _grouped(table(s, d, "part").cube("p_type", "p_brand"))


@op(_GROUPED + "ROLLUP (p_type, p_brand)")
def op_rollup(s, d):
    return _grouped(table(s, d, "part").rollup("p_type", "p_brand"))


def _grouped(g):
    return g.agg(F.count(F.lit(1)).alias("n"), F.max("p_size").alias("most")).select(F.coalesce("p_type", F.lit("*")).alias("p_type"), F.coalesce("p_brand", F.lit("*")).alias("p_brand"), "n", "most")


@op(_GROUPED + "GROUPING SETS ((p_type), (p_brand), ())")
def op_grouping_sets(s, d):
    table(s, d, "part").createOrReplaceTempView("op_part")
    return s.sql(_GROUPED.replace("FROM part", "FROM op_part") + "GROUPING SETS ((p_type), (p_brand), ())")


@op("SELECT p_brand, count(*) AS n, count(DISTINCT p_type) AS types, round(avg(p_retailprice), 4) AS mean, round(stddev_samp(p_retailprice), 4) AS dev, bit_or(p_size) AS bits, bool_and(p_size > 0) AS all_positive FROM part GROUP BY p_brand HAVING count(*) > 1")
def op_aggregates(s, d):
    a = table(s, d, "part").groupBy("p_brand").agg(F.count(F.lit(1)).alias("n"), F.countDistinct("p_type").alias("types"), F.round(F.avg("p_retailprice"), 4).alias("mean"), F.round(F.stddev_samp("p_retailprice"), 4).alias("dev"), F.bit_or("p_size").alias("bits"), F.bool_and(F.col("p_size") > 0).alias("all_positive"))
    return a.where("n > 1")


@op("SELECT p_partkey, rank() OVER w AS r, dense_rank() OVER w AS dr, row_number() OVER (PARTITION BY p_type ORDER BY p_size, p_partkey) AS rn, ntile(4) OVER (PARTITION BY p_type ORDER BY p_size, p_partkey) AS q FROM part WINDOW w AS (PARTITION BY p_type ORDER BY p_size)")
def op_rank(s, d):
    w, u = Window.partitionBy("p_type").orderBy("p_size"), Window.partitionBy("p_type").orderBy("p_size", "p_partkey")
    return table(s, d, "part").select("p_partkey", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("dr"), F.row_number().over(u).alias("rn"), F.ntile(4).over(u).alias("q"))


@op("SELECT o_orderkey, round(sum(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderkey ROWS UNBOUNDED PRECEDING), 2) AS total, lag(o_orderkey, 1, -1) OVER (PARTITION BY o_custkey ORDER BY o_orderkey) AS before, lead(o_orderkey, 1, -1) OVER (PARTITION BY o_custkey ORDER BY o_orderkey) AS after FROM orders")
def op_running_sum(s, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderkey")
    return table(s, d, "orders").select("o_orderkey", F.round(F.sum("o_totalprice").over(w.rowsBetween(Window.unboundedPreceding, 0)), 2).alias("total"), F.lag("o_orderkey", 1, -1).over(w).alias("before"), F.lead("o_orderkey", 1, -1).over(w).alias("after"))


@op("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 3600000000 PRECEDING AND CURRENT ROW) AS n, max(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND 2 FOLLOWING) AS most FROM events")
def op_frame(s, d):
    e = table(s, d, "events").withColumn("t", windows.micros("ts"))
    hour = Window.partitionBy("user_id").orderBy("t").rangeBetween(-3_600_000_000, 0)
    near = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-2, 2)
    return e.select("event_id", F.count(F.lit(1)).over(hour).alias("n"), F.max("value").over(near).alias("most"))


@op("SELECT p_type, p_partkey, p_retailprice FROM (SELECT *, row_number() OVER (PARTITION BY p_type ORDER BY p_retailprice DESC, p_partkey) AS r FROM part) WHERE r <= 3")
def op_topk(s, d):
    w = Window.partitionBy("p_type").orderBy(F.desc("p_retailprice"), "p_partkey")
    return table(s, d, "part").withColumn("r", F.row_number().over(w)).where("r <= 3").select("p_type", "p_partkey", "p_retailprice")


def _sides(s, d):
    l = table(s, d, "lineitem")  # noqa: E741
    return l.where("l_quantity > 45").select(F.col("l_partkey").alias("k")), l.where("l_discount > 0.08").select(F.col("l_partkey").alias("k"))


_A, _B = "SELECT l_partkey AS k FROM lineitem WHERE l_quantity > 45", "SELECT l_partkey AS k FROM lineitem WHERE l_discount > 0.08"


@op(f"{_A} UNION {_B}")
def op_union(s, d):
    a, b = _sides(s, d)
    return a.unionByName(b).distinct()


@op(f"{_A} INTERSECT ALL {_B}")
def op_intersect(s, d):
    a, b = _sides(s, d)
    return a.intersectAll(b)


@op(f"{_A} EXCEPT ALL {_B}")
def op_except(s, d):
    a, b = _sides(s, d)
    return a.exceptAll(b)


@op("SELECT event_type, CAST(sum(CAST(json_extract(props, '$.k') AS BIGINT)) AS BIGINT) AS total FROM events GROUP BY event_type")
def op_json(s, d):
    return table(s, d, "events").groupBy("event_type").agg(F.sum(F.get_json_object("props", "$.k").cast("long")).alias("total"))


@op("SELECT page_id, count(*) AS links, min(t) AS first FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]+)\"', 1)) AS t FROM pages) GROUP BY page_id")
def op_regex_links(s, d):
    t = table(s, d, "pages").select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]+)"'))).alias("t"))
    return t.groupBy("page_id").agg(F.count(F.lit(1)).alias("links"), F.min("t").alias("first"))


@op("SELECT vec_id, list_position(l, list_max(l)) AS at, len(list_filter(l, lambda x: x > 0)) AS positive, round(list_sum(list_transform(l, lambda x: x * x)), 4) AS norm2 FROM (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS l FROM embeddings)")
def op_array(s, d):
    v = table(s, d, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("l"))
    return v.select("vec_id", F.array_position("l", F.array_max("l")).alias("at"), F.size(F.filter("l", lambda x: x > 0)).alias("positive"), F.round(F.aggregate("l", F.lit(0.0), lambda a, x: a + x * x), 4).alias("norm2"))


@op("SELECT user_id, count(*) FILTER (event_type = 'click') AS clicks, count(DISTINCT event_type) AS kinds FROM events GROUP BY user_id")
def op_map(s, d):
    """Counts by type gathered in a map of at most five keys, then read by key."""
    n = table(s, d, "events").groupBy("user_id", "event_type").count()
    m = n.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "count"))).alias("m"))
    return m.select("user_id", F.coalesce(F.col("m")["click"], F.lit(0)).alias("clicks"), F.size(F.map_keys("m")).alias("kinds"))


@op("SELECT strftime(o_orderdate, '%Y-%m') AS month, count(*) AS n, CAST(min(dayofweek(o_orderdate)) + 1 AS BIGINT) AS first_day FROM orders GROUP BY 1")
def op_date(s, d):
    return table(s, d, "orders").groupBy(F.date_format("o_orderdate", "yyyy-MM").alias("month")).agg(F.count(F.lit(1)).alias("n"), F.min(F.dayofweek("o_orderdate")).cast("long").alias("first_day"))


@op("SELECT o_custkey, count(*) FILTER (o_orderstatus = 'F') AS f, count(*) FILTER (o_orderstatus = 'O') AS o, count(*) FILTER (o_orderstatus = 'P') AS p FROM orders GROUP BY o_custkey")
def op_pivot(s, d):
    p = table(s, d, "orders").groupBy("o_custkey").pivot("o_orderstatus", ["F", "O", "P"]).agg(F.count(F.lit(1)))
    return p.select("o_custkey", *[F.coalesce(c, F.lit(0)).alias(c.lower()) for c in ("F", "O", "P")])


@op("SELECT l_returnflag, round(quantile_cont(l_extendedprice, 0.5), 4) AS median, round(quantile_cont(l_extendedprice, 0.9), 4) AS p90 FROM lineitem GROUP BY l_returnflag")
def op_percentile(s, d):
    return table(s, d, "lineitem").groupBy("l_returnflag").agg(F.round(F.percentile("l_extendedprice", F.lit(0.5)), 4).alias("median"), F.round(F.percentile("l_extendedprice", F.lit(0.9)), 4).alias("p90"))


@op("SELECT p_partkey, CAST(sqrt(p_size) * 1000 AS BIGINT) AS root, log10(p_retailprice) > 3 AS dear, (p_size & 7) AS low, upper(substr(p_name, 1, 3)) AS start FROM part")
def op_scalar(s, d):
    return table(s, d, "part").select("p_partkey", F.round(F.sqrt("p_size") * 1000).cast("long").alias("root"), (F.log10("p_retailprice") > 3).alias("dear"), F.col("p_size").bitwiseAND(7).alias("low"), F.upper(F.substring("p_name", 1, 3)).alias("start"))


@op("SELECT c_mktsegment, round(sum(c_acctbal), 2) AS total FROM customer GROUP BY c_mktsegment")
def op_udf(s, d):
    """A grouped-aggregate pandas UDF: vectorized, for what built-in aggregates lack."""

    @F.pandas_udf("double")
    def total(v: pd.Series) -> float:
        return float(v.sum())

    return table(s, d, "customer").groupBy("c_mktsegment").agg(F.round(total("c_acctbal"), 2).alias("total"))


@op("SELECT p_partkey, CAST(code AS BIGINT) AS code, CAST(a AS BIGINT) AS a, CAST(b AS BIGINT) AS b FROM (SELECT p_partkey, [1, 3, 5, 7][p_size % 4 + 1] AS code FROM part) JOIN (VALUES (1, 0, 1), (2, 0, 2), (4, 1, 2)) t(bit, a, b) ON code & bit > 0")
def op_udtf(s, d):
    """A table function that decodes the edges of a three-vertex quick code, one of four for each part by its size."""
    formats.register_functions(s)
    table(s, d, "part").selectExpr("p_partkey", "element_at(array(1L, 3L, 5L, 7L), cast(p_size % 4 as int) + 1) AS code").createOrReplaceTempView("op_codes")
    return s.sql("SELECT p_partkey, code, a, b FROM op_codes, LATERAL decode_code(code)")


@op("SELECT src AS a, dst AS b FROM (SELECT a.l_partkey AS src, b.l_partkey AS dst FROM (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem) a JOIN (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem) b ON a.l_orderkey = b.l_orderkey AND a.l_partkey < b.l_partkey GROUP BY ALL HAVING count(*) >= 2)")
def op_edge_list_round_trip(s, d):
    """A graph's edges written as text lines "src dst" and read back."""
    return formats.edge_list_round_trip(copart(s, d, 2))


_PAIRS = "SELECT least(c, s) AS a, greatest(c, s) AS b, min(p) AS e FROM (SELECT 2 * o_custkey AS c, 2 * l_suppkey + 1 AS s, o_orderpriority AS p FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE l_returnflag = 'R' AND l_quantity >= 45) GROUP BY ALL"


@op(_PAIRS)
def op_json_round_trip(s, d):
    """A graph's labelled edges as JSON lines, read back with their schema."""
    return formats.pairs_round_trip(custsupp(s, d, 45), "json")


@op(_PAIRS)
def op_orc_round_trip(s, d):
    """The same as ORC files."""
    return formats.pairs_round_trip(custsupp(s, d, 45), "orc")


_TUMBLE = "SELECT CAST(epoch_us(ts) // 3600000000 AS BIGINT) AS hour, event_type, count(*) AS n FROM events GROUP BY ALL"


@op(_TUMBLE)
def op_window_tumbling(s, d):
    return windows.tumbling(table(s, d, "events"), 60)


@op(_TUMBLE)
def op_stream_tumbling(s, d):
    """The same through Structured Streaming, run to the end of the input."""
    return windows.stream_tumbling(s, f"{d}/events.parquet", 60)


@op("SELECT w AS start, count(*) AS n FROM (SELECT unnest([epoch_us(ts) // 1800000000, epoch_us(ts) // 1800000000 - 1]) AS w FROM events) GROUP BY w")
def op_window_sliding(s, d):
    return windows.sliding(table(s, d, "events"), 60, 30)


@op("SELECT user_id, count(*) AS sessions, max(n) AS longest FROM (SELECT user_id, session, count(*) AS n FROM (SELECT user_id, sum(CAST(gap AS INT)) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS session FROM (SELECT user_id, ts, event_id, coalesce(epoch_us(ts) - epoch_us(lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id)) >= 3600000000, true) AS gap FROM events)) GROUP BY ALL) GROUP BY user_id")
def op_session(s, d):
    return windows.sessions(table(s, d, "events"), 60)


@op("SELECT CAST(late AS BOOLEAN) AS late, count(*) AS n FROM (SELECT epoch_us(ts) < max(epoch_us(ts)) OVER (ORDER BY event_id ROWS UNBOUNDED PRECEDING) - 60000000 AS late FROM events) GROUP BY late")
def op_late(s, d):
    """Events more than a minute behind the greatest time seen before them in arrival order."""
    return windows.late(table(s, d, "events"), 60_000_000)


@op("SELECT least(a.user_id, b.user_id) AS a, greatest(a.user_id, b.user_id) AS b FROM events a JOIN events b ON a.event_type = 'error' AND b.event_type = 'error' AND a.user_id < b.user_id AND abs(epoch_us(a.ts) - epoch_us(b.ts)) <= 600000000 GROUP BY ALL")
def op_stream_pairs(s, d):
    """Edges between users with errors within ten minutes, from a stream-stream interval join."""
    return windows.stream_pairs(s, f"{d}/events.parquet", "error", 10)


@op("SELECT user_id, count(*) AS value FROM events GROUP BY user_id")
def op_stream_counters(s, d):
    """Stateful counters of events by user (applyInPandasWithState)."""
    return windows.stream_counters(s, f"{d}/events.parquet")


@op("SELECT user_id, event_type, count(*) AS n FROM (SELECT DISTINCT event_id, user_id, event_type FROM events) GROUP BY ALL")
def op_stream_distinct(s, d):
    """Events by user and type, each id once within the watermark."""
    found = windows.stream_distinct(s, f"{d}/events.parquet", ["event_id"], "3650 days")
    return found.groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("n"))


@op("""WITH e AS (SELECT a.user_id AS src, b.user_id AS dst FROM events a JOIN events b ON a.event_type = 'error' AND b.event_type = 'error' AND a.user_id < b.user_id AND abs(epoch_us(a.ts) - epoch_us(b.ts)) <= 300000000 GROUP BY ALL),
deg AS (SELECT v, count(*) AS d FROM (SELECT unnest([src, dst]) AS v FROM e) GROUP BY v),
tri AS (SELECT count(*) AS t FROM e a JOIN e b ON a.dst = b.src JOIN e c ON c.src = a.src AND c.dst = b.dst)
SELECT CAST(n_edges AS BIGINT) AS n_edges, CAST(n AS BIGINT) AS n FROM (SELECT 2 AS n_edges, (SELECT sum(d * (d - 1) // 2) FROM deg) - 3 * (SELECT t FROM tri) AS n UNION ALL SELECT 3, (SELECT t FROM tri)) WHERE n > 0""")
def op_stream_mining(s, d):
    """Motifs of three users with errors within five minutes, mined again after each micro-batch: the last result."""
    results = windows.mine_each_batch(s, f"{d}/events.parquet", lambda g: motifs.count_motifs(g, 3).select("n_edges", "n"), "error", 5)
    return results[-1]


def queries() -> dict[str, Query]:
    return dict(_queries)


def oracle_sql() -> dict[str, str]:
    return dict(_sql)
