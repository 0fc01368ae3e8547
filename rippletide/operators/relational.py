"""General operators on graph and event tables that users of the methods need, each with its SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from rippletide.plans.storage import holding, stored
from rippletide.sources.tables import table


def as_of(left: DataFrame, right: DataFrame, by: str, at: str, value: str) -> DataFrame:
    """Each left row (id, by, at) with the latest right value at or before it: both sides interleave in
    one window per key, so no pair is built."""
    a = left.select("id", by, F.col(at).alias("at"), F.lit(None).cast(right.schema[value].dataType).alias("x"), F.lit(1).alias("side"))
    b = right.select(F.lit(None).cast("long").alias("id"), by, F.col(at).alias("at"), F.col(value).alias("x"), F.lit(0).alias("side"))
    upto = Window.partitionBy(by).orderBy("at", "side").rowsBetween(Window.unboundedPreceding, 0)
    return a.union(b).withColumn("last", F.last("x", ignorenulls=True).over(upto)).where("side = 1").select("id", F.col("last").alias(value))


def range_join(left: DataFrame, right: DataFrame, by: str, at: str, within: int) -> DataFrame:
    """Pairs (id, rid) of one key at most ``within`` seconds apart, right after left: rows meet through
    time buckets of that width, the right side in its own and the one before."""
    seconds = F.unix_timestamp(F.col(at).cast("timestamp"))
    a = left.select("id", by, seconds.alias("ta"), F.floor(seconds / within).alias("bucket"))
    b = right.select(F.col("id").alias("rid"), by, seconds.alias("tb"), F.explode(F.array(F.floor(seconds / within), F.floor(seconds / within) - 1)).alias("bucket"))
    return a.join(b, [by, "bucket"]).where((F.col("tb") > F.col("ta")) & (F.col("tb") - F.col("ta") <= within)).select("id", "rid")


@F.udtf(returnType="k: int, square: int")
class Squares:
    """k and its square for k in 1..n."""

    def eval(self, n: int):
        for k in range(1, n + 1):
            yield k, k * k


def _events(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "events").select(F.col("event_id").alias("id"), "user_id", "event_type", "ts", "value", "props")


def _asof(s: SparkSession, d: str) -> DataFrame:
    e = _events(s, d)
    return as_of(e.where("event_type = 'purchase'"), e.where("event_type = 'click'"), "user_id", "ts", "value")


def _udaf(s: SparkSession, d: str) -> DataFrame:
    @F.pandas_udf("double", F.PandasUDFType.GROUPED_AGG)
    def spread(v):
        return float(v.max() - v.min())

    return table(s, d, "customer").groupBy("c_mktsegment").agg(spread("c_acctbal").alias("span"))


def _udf(s: SparkSession, d: str) -> DataFrame:
    @F.pandas_udf(T.LongType())
    def low(k):
        return k % 7

    return table(s, d, "part").select("p_partkey", low("p_partkey").alias("m"))


def _recursive(s: SparkSession, d: str) -> DataFrame:
    """The key of every customer with orders, doubled five times. Stored, as the limit on a recursion's rows is lifted for it only."""
    with holding(s, {"spark.sql.cteRecursionRowLimit": "-1"}):
        return stored(s.sql("WITH RECURSIVE r(id, depth) AS (SELECT DISTINCT o_custkey, 0 FROM {o} UNION ALL SELECT id * 2, depth + 1 FROM r WHERE depth < 5) SELECT id, depth FROM r", o=table(s, d, "orders")), "recursive")


E_ = "(SELECT event_id id, user_id, event_type, ts, value, props FROM events)"
OPS: dict[str, tuple[Callable[[SparkSession, str], DataFrame], str]] = {
    "op_semi": (lambda s, d: table(s, d, "customer").join(table(s, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey"), "SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders)"),
    "op_anti": (lambda s, d: table(s, d, "part").join(table(s, d, "lineitem").where("l_quantity > 49"), F.col("p_partkey") == F.col("l_partkey"), "left_anti").select("p_partkey"), "SELECT p_partkey FROM part WHERE p_partkey NOT IN (SELECT l_partkey FROM lineitem WHERE l_quantity>49)"),
    "op_asof": (_asof, f"SELECT a.id, (SELECT b.value FROM {E_} b WHERE b.user_id=a.user_id AND b.event_type='click' AND b.ts<=a.ts ORDER BY b.ts DESC LIMIT 1) AS value FROM {E_} a WHERE a.event_type='purchase'"),
    "op_range_join": (
        lambda s, d: range_join(_events(s, d).where("event_type = 'click'"), _events(s, d).where("event_type = 'purchase'"), "user_id", "ts", 3600),
        f"SELECT a.id, b.id rid FROM {E_} a JOIN {E_} b ON a.user_id=b.user_id AND a.event_type='click' AND b.event_type='purchase' AND floor(epoch(b.ts))>floor(epoch(a.ts)) AND floor(epoch(b.ts))-floor(epoch(a.ts))<=3600",
    ),
    "op_rollup": (lambda s, d: table(s, d, "orders").rollup("o_orderstatus", "o_orderpriority").agg(F.count(F.lit(1)).alias("n")), "SELECT o_orderstatus, o_orderpriority, CAST(count(*) AS BIGINT) n FROM orders GROUP BY ROLLUP (o_orderstatus, o_orderpriority)"),
    "op_cube": (lambda s, d: table(s, d, "lineitem").cube("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n")), "SELECT l_returnflag, l_linestatus, CAST(count(*) AS BIGINT) n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)"),
    "op_grouping_sets": (
        lambda s, d: table(s, d, "lineitem").groupingSets([[F.col("l_returnflag")], [F.col("l_linestatus")]], "l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n")),
        "SELECT l_returnflag, l_linestatus, CAST(count(*) AS BIGINT) n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus))",
    ),
    "op_rank": (
        lambda s, d: table(s, d, "customer").select("c_custkey", *[f().over(Window.partitionBy("c_nationkey").orderBy(F.desc("c_acctbal"), "c_custkey")).alias(n) for n, f in (("rn", F.row_number), ("rk", F.rank), ("dr", F.dense_rank))]),
        "SELECT c_custkey, CAST(row_number() OVER w AS INTEGER) rn, CAST(rank() OVER w AS INTEGER) rk, CAST(dense_rank() OVER w AS INTEGER) dr FROM customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey)",
    ),
    "op_frames": (
        lambda s, d: _events(s, d).select("id", F.round(F.sum("value").over(Window.partitionBy("user_id").orderBy("ts").rowsBetween(-2, 0)), 4).alias("moving"), F.lag("id").over(Window.partitionBy("user_id").orderBy("ts")).alias("prev")),
        f"SELECT id, round(sum(value) OVER (PARTITION BY user_id ORDER BY ts ROWS 2 PRECEDING),4) moving, lag(id) OVER (PARTITION BY user_id ORDER BY ts) prev FROM {E_}",
    ),
    "op_setops": (lambda s, d: table(s, d, "customer").select("c_nationkey").intersect(table(s, d, "supplier").select("s_nationkey")).exceptAll(table(s, d, "nation").where("n_regionkey = 0").select("n_nationkey")), "(SELECT c_nationkey FROM customer INTERSECT SELECT s_nationkey FROM supplier) EXCEPT SELECT n_nationkey FROM nation WHERE n_regionkey=0"),
    "op_pivot": (
        lambda s, d: table(s, d, "lineitem").groupBy("l_returnflag").pivot("l_linestatus", ["O", "F"]).agg(F.count(F.lit(1))).select("l_returnflag", F.coalesce("O", F.lit(0)).alias("open_n"), F.coalesce("F", F.lit(0)).alias("full_n")),
        "SELECT l_returnflag, CAST(count(*) FILTER (WHERE l_linestatus='O') AS BIGINT) open_n, CAST(count(*) FILTER (WHERE l_linestatus='F') AS BIGINT) full_n FROM lineitem GROUP BY 1",
    ),
    "op_unpivot": (lambda s, d: table(s, d, "part").select("p_partkey", F.col("p_size").cast("double").alias("p_size"), "p_retailprice").unpivot("p_partkey", ["p_size", "p_retailprice"], "measure", "amount"), "SELECT p_partkey, 'p_size' measure, p_size::DOUBLE amount FROM part UNION ALL SELECT p_partkey, 'p_retailprice', p_retailprice FROM part"),
    "op_json": (lambda s, d: _events(s, d).select("id", F.from_json("props", "k int").getField("k").alias("k")), f"SELECT id, CAST(json_extract_string(props,'$.k') AS INTEGER) k FROM {E_}"),
    "op_strings": (lambda s, d: table(s, d, "pages").select("page_id", F.regexp_extract("url", "https?://([^/]+)", 1).alias("host"), F.md5("url").alias("h")), "SELECT page_id, regexp_extract(url,'https?://([^/]+)',1) host, md5(url) h FROM pages"),
    "op_dates": (lambda s, d: table(s, d, "orders").groupBy(F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m")).agg(F.count(F.lit(1)).alias("n")), "SELECT CAST(year(o_orderdate) AS INTEGER) y, CAST(month(o_orderdate) AS INTEGER) m, CAST(count(*) AS BIGINT) n FROM orders GROUP BY 1, 2"),
    "op_math": (lambda s, d: table(s, d, "part").select("p_partkey", F.round(F.sqrt("p_retailprice") + F.log("p_retailprice"), 5).alias("x")), "SELECT p_partkey, round(sqrt(p_retailprice)+ln(p_retailprice),5) x FROM part"),
    "op_arrays": (lambda s, d: table(s, d, "embeddings").select("vec_id", F.size("embedding").alias("n"), F.round(F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x * x), 4).alias("norm2")), "SELECT vec_id, CAST(len(embedding) AS INTEGER) n, round(list_inner_product(CAST(embedding AS DOUBLE[]), CAST(embedding AS DOUBLE[])),4) norm2 FROM embeddings"),
    "op_maps": (lambda s, d: table(s, d, "nation").groupBy("n_regionkey").agg(F.map_from_entries(F.collect_list(F.struct("n_nationkey", "n_name"))).alias("m")).select("n_regionkey", F.size("m").alias("n")), "SELECT n_regionkey, CAST(count(*) AS INTEGER) n FROM nation GROUP BY 1"),
    "op_udf": (_udf, "SELECT p_partkey, p_partkey % 7 m FROM part"),
    "op_udaf": (_udaf, "SELECT c_mktsegment, max(c_acctbal)-min(c_acctbal) span FROM customer GROUP BY 1"),
    "op_udtf": (
        lambda s, d: table(s, d, "orders").groupBy("o_custkey").agg(F.count(F.lit(1)).cast("int").alias("n")).lateralJoin(Squares(F.col("n").outer())).select("o_custkey", "k", "square"),
        "SELECT o_custkey, CAST(k AS INTEGER) k, CAST(k*k AS INTEGER) square FROM (SELECT o_custkey, count(*) n FROM orders GROUP BY 1), LATERAL (SELECT unnest(range(1, n+1)) k)",
    ),
    "op_recursive": (
        _recursive,
        "WITH RECURSIVE r(id, depth) AS (SELECT DISTINCT o_custkey, 0 FROM orders UNION ALL SELECT id * 2, depth + 1 FROM r WHERE depth < 5) SELECT id, depth FROM r",
    ),
}


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {k: f for k, (f, _) in OPS.items()}


def oracles() -> dict[str, str]:
    return {k: q for k, (_, q) in OPS.items()}
