"""Relational surface around the methods: joins in time and range, grouping, windows, sets, recursion, scalar families.

Each is a DataFrame plan over the given tables. Time joins never compare all rows with all: they meet by bucket or by one ordered window.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..plans.state import kept
from ..sources import gradients as G

table = G.table


def asof(left: DataFrame, right: DataFrame, key: str, time: str, value: str) -> DataFrame:
    """``left`` with ``value`` of the latest row of ``right`` with the same key at the same time or before: one union, one ordered window, no join."""
    a = left.withColumn("side", F.lit(1)).withColumn(value, F.lit(None).cast(right.schema[value].dataType))
    b = right.select(key, time, value).withColumn("side", F.lit(0))
    order = Window.partitionBy(key).orderBy(time, "side").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return a.unionByName(b, allowMissingColumns=True).withColumn(value, F.last(value, ignorenulls=True).over(order)).where("side = 1").drop("side")


def within(left: DataFrame, right: DataFrame, key: str, seconds: int) -> DataFrame:
    """Pairs with equal key whose right time ``rt`` is at most so many seconds before the left time ``lt``: equal buckets, each left row in two of them."""
    bucket = lambda c: F.floor(F.unix_timestamp(c) / seconds)
    a = left.withColumn("bucket", F.explode(F.array(bucket("lt"), bucket("lt") - 1)))
    near = a.join(right.withColumn("bucket", bucket("rt")), [key, "bucket"]).drop("bucket")
    apart = F.unix_timestamp("lt") - F.unix_timestamp("rt")
    return near.where((apart >= 0) & (apart <= seconds))


def errors_before_purchases(s: SparkSession, d: str) -> DataFrame:
    e = table(s, d, "events")
    p = e.where("event_type = 'purchase'").select("event_id", "user_id", "ts")
    found = asof(p, e.where("event_type = 'error'").select("user_id", "ts", F.col("event_id").alias("error_id")), "user_id", "ts", "error_id")
    return found.select("event_id", F.coalesce("error_id", F.lit(-1)).alias("error_id"))


def hour_before_purchases(s: SparkSession, d: str) -> DataFrame:
    e = table(s, d, "events").select("event_id", "user_id", "event_type", F.date_trunc("second", F.col("ts").cast("timestamp")).alias("t"))
    p = e.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase_id"), "user_id", F.col("t").alias("lt"))
    o = e.where("event_type <> 'purchase'").select(F.col("event_id").alias("other_id"), "user_id", F.col("t").alias("rt"))
    return within(p, o, "user_id", 3600).select("purchase_id", "other_id")


def ordered(*more: str) -> Window:
    return Window.partitionBy("l_orderkey").orderBy(*more)


LINE = ("l_extendedprice", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity")


def top_lines(s: SparkSession, d: str) -> DataFrame:
    best = ordered(F.desc("l_extendedprice"), "l_partkey", "l_linenumber", "l_suppkey")
    lines = table(s, d, "lineitem").select("l_orderkey", *LINE)
    return lines.withColumn("r", F.row_number().over(best)).where("r <= 2").select("l_orderkey", "r", "l_extendedprice")


def norms(s: SparkSession, d: str, grouping: str) -> DataFrame:
    """Energy by step and worker and their totals; -1 stands for all."""
    g = G.quarterly(s, d)
    grouped = g.groupingSets([["step"], ["worker"], []], "step", "worker") if grouping == "sets" else getattr(g, grouping)("step", "worker")
    out = grouped.agg(F.sum(F.col("v") * F.col("v")).alias("energy"))
    return out.select(*[F.coalesce(c, F.lit(-1)).alias(c) for c in ("step", "worker")], F.round("energy", 2).alias("energy"))


def type_counts(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "events").groupBy(F.hour("ts").alias("hour")).pivot("event_type", G.EVENTS).agg(F.count(F.lit(1))).na.fill(0)


def sessions(s: SparkSession, d: str) -> DataFrame:
    """Sessions of a user end after 30 minutes without an event."""
    order = Window.partitionBy("user_id").orderBy("t", "event_id")
    e = table(s, d, "events").select("user_id", "event_id", F.unix_timestamp(F.col("ts").cast("timestamp")).alias("t"))
    begins = (F.col("t") - F.lag("t").over(order) >= 1800) | F.lag("t").over(order).isNull()
    numbered = e.withColumn("begins", begins.cast("int")).withColumn("n", F.sum("begins").over(order))
    return numbered.groupBy("user_id", "n").agg(F.min("t").alias("first"), F.max("t").alias("last"), F.count(F.lit(1)).alias("events")).select("user_id", "first", "last", "events")


def sliding(s: SparkSession, d: str) -> DataFrame:
    """Windows of a day that begin every six hours: value in cents by kind of event."""
    e = table(s, d, "events").select(F.unix_timestamp(F.col("ts").cast("timestamp")).alias("t"), "event_type", F.round(F.col("value") * 100).cast("bigint").alias("cents"))
    begin = F.explode(F.transform(F.sequence(F.lit(0), F.lit(3)), lambda k: (F.floor(F.col("t") / 21600) - k) * 21600))
    return e.withColumn("begin", begin).groupBy("begin", "event_type").agg(F.sum("cents").alias("cents"))


def dot(a: str, b: str) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda acc, x: acc + x)


def neighbours(s: SparkSession, d: str) -> DataFrame:
    """Inner product of each vector with the next one by number."""
    e = table(s, d, "embeddings")
    after = e.select((F.col("vec_id") - 1).alias("vec_id"), F.col("embedding").alias("next"))
    return e.join(after, "vec_id").select("vec_id", F.round(dot("embedding", "next"), 5).alias("dot"))


def schedule(s: SparkSession, d: str) -> DataFrame:
    """Each week with orders, as an epoch, with its share of the learning rate, from a table of ranges."""
    ranges = s.createDataFrame([(0, 150, 1.0), (150, 250, 0.1), (250, None, 0.01)], "low int, high int, factor double")
    inside = (F.col("epoch") >= F.col("low")) & (F.col("high").isNull() | (F.col("epoch") < F.col("high")))
    return G.order_weeks(s, d).join(F.broadcast(ranges), inside).select("epoch", "factor")


def recursive(s: SparkSession, d: str) -> DataFrame:
    """Momentum over the samples of the quarters in their order, by recursion."""
    n = kept(G.quarters(s, d).select((F.row_number().over(Window.orderBy("step")) - 1).alias("place"), "step", "samples"), "quarters")
    last = n.count() - 1
    sql = "with recursive r(k, step, m) as (select place, step, cast(samples as double) from {n} where place = 0 union all select k + 1, n.step, 0.9D * m + n.samples from r join {n} n on n.place = r.k + 1 where k < {last}) select step, round(m, 6) as m from r"
    return s.sql(sql, n=n, last=last)


def sparse_sum(s: SparkSession, d: str) -> DataFrame:
    """Messages as maps from position to value, merged two workers at a time."""
    g = G.quarterly(s, d, 2).where("step < 3 and i < 3").withColumn("f", F.col("i") * 50 + F.col("j"))
    maps = g.groupBy("step").pivot("worker", [0, 1]).agg(F.map_from_entries(F.collect_list(F.struct("f", "v")))).select("step", F.col("0").alias("a"), F.col("1").alias("b"))
    merged = F.map_zip_with("a", "b", lambda k, x, y: F.coalesce(x, F.lit(0.0)) + F.coalesce(y, F.lit(0.0)))
    return maps.select("step", F.explode(merged).alias("f", "v"))


def ranked_cells(s: SparkSession, d: str) -> DataFrame:
    cell = Window.partitionBy("step").orderBy(F.desc("v"), "i", "j")
    sums = G.quarterly(s, d).groupBy("step", "i", "j").agg(F.sum("v").alias("v"))
    place = F.rank().over(Window.partitionBy("step").orderBy(F.desc("v")))
    return sums.select("step", "i", "j", F.row_number().over(cell).alias("row"), place.alias("place"), F.ntile(4).over(cell).alias("quarter"))


def weekly(s: SparkSession, d: str) -> DataFrame:
    """Moving sum over days; a row for each day, so one task holds them."""
    day = F.datediff(F.to_date("ts"), F.lit("2024-01-01").cast("date")).alias("day")
    sums = table(s, d, "events").groupBy(day).agg(F.sum(F.round(F.col("value") * 100).cast("bigint")).alias("cents"))
    return sums.select("day", F.sum("cents").over(Window.orderBy("day").rowsBetween(-6, 0)).alias("week"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "filter_project": lambda s, d: table(s, d, "lineitem").where("l_quantity between 10 and 12 and l_returnflag in ('A', 'R') and l_linestatus <=> 'F'").select("l_orderkey", "l_linenumber", F.round(F.col("l_extendedprice") * (1 - F.col("l_discount")), 4).alias("price")),
        "smj_order_lines": lambda s, d: table(s, d, "orders").join(table(s, d, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("l_quantity").cast("bigint")).alias("quantity")),
        "merge_memory": lambda s, d: G.quarterly(s, d).where("step = 0").select("worker", "i", "j", F.col("v").alias("a")).join(G.quarterly(s, d).where("step = 1").select("worker", "i", "j", F.col("v").alias("b")), ["worker", "i", "j"], "full").select("worker", "i", "j", (F.coalesce("a", F.lit(0.0)) + F.coalesce("b", F.lit(0.0))).alias("v")),
        "unlabelled_docs": lambda s, d: table(s, d, "documents").select("doc_id").join(table(s, d, "labels"), "doc_id", "left_anti"),
        "range_join_schedule": schedule,
        "interval_join_events": hour_before_purchases,
        "asof_join_events": errors_before_purchases,
        "nlj_nation_pairs": lambda s, d: table(s, d, "nation").select(F.col("n_nationkey").alias("a")).join(F.broadcast(table(s, d, "nation").select(F.col("n_nationkey").alias("b"))), F.col("a") < F.col("b")),
        "lateral_topk": top_lines,
        "agg_basic": lambda s, d: table(s, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("l_quantity").cast("bigint")).alias("quantity"), F.count_if(F.col("l_tax") > 0.05).alias("taxed"), F.max("l_extendedprice").alias("most")),
        "agg_distinct": lambda s, d: table(s, d, "lineitem").groupBy("l_returnflag").agg(F.count_distinct("l_partkey").alias("parts"), F.count_distinct("l_suppkey").alias("suppliers")),
        "norm_cube": lambda s, d: norms(s, d, "cube"),
        "norm_rollup": lambda s, d: norms(s, d, "rollup"),
        "norm_grouping_sets": lambda s, d: norms(s, d, "sets"),
        "pivot_types": type_counts,
        "unpivot_types": lambda s, d: type_counts(s, d).unpivot(["hour"], G.EVENTS, "event_type", "n"),
        "top_cells_rank": ranked_cells,
        "momentum_window": weekly,
        "top_cells_global": lambda s, d: G.quarterly(s, d).orderBy(F.desc("v"), "step", "worker", "i", "j").limit(20),
        "support_union": lambda s, d: G.quarterly(s, d).where("step = 0").select("i", "j").union(G.quarterly(s, d).where("step = 1").select("i", "j")).distinct(),
        "support_intersect": lambda s, d: G.quarterly(s, d).where("step = 0").select("i", "j").intersect(G.quarterly(s, d).where("step = 1").select("i", "j")),
        "support_except": lambda s, d: G.quarterly(s, d).where("step = 0").select("i", "j").subtract(G.quarterly(s, d).where("step = 1").select("i", "j")),
        "lr_schedule_recursive": recursive,
        "hash_sample": lambda s, d: table(s, d, "orders").where(F.conv(F.substring(F.md5(F.col("o_orderkey").cast("string")), 1, 8), 16, 10).cast("bigint") < F.lit(2**32 // 10)).select("o_orderkey"),
        "dedup_docs": lambda s, d: table(s, d, "documents").groupBy(F.md5("text").alias("digest")).agg(F.min("doc_id").alias("doc_id")).select("doc_id"),
        "html_strip": lambda s, d: table(s, d, "pages").select("page_id", F.length(F.regexp_replace("html", "<[^>]*>", "")).alias("n")),
        "quarter_steps": lambda s, d: table(s, d, "orders").groupBy(((F.year("o_orderdate") - 1995) * 4 + F.quarter("o_orderdate") - 1).alias("step")).agg(F.count(F.lit(1)).alias("n")),
        "softmax_probs": lambda s, d: table(s, d, "part").groupBy("p_type").agg(F.count(F.lit(1)).alias("n")).select("p_type", F.round(F.exp(F.col("n") / 1000.0) / F.sum(F.exp(F.col("n") / 1000.0)).over(Window.partitionBy()), 6).alias("p")),
        "embedding_dot": neighbours,
        "embedding_norm": lambda s, d: table(s, d, "embeddings").select("vec_id", F.round(F.sqrt(dot("embedding", "embedding")), 5).alias("norm")),
        "sparse_map_merge": sparse_sum,
        "json_props": lambda s, d: table(s, d, "events").groupBy(F.get_json_object("props", "$.k").cast("int").alias("k")).agg(F.count(F.lit(1)).alias("n")),
        "sliding_gradient": sliding,
        "session_events": sessions,
        "scan_counts": lambda s, d: table(s, d, "region").agg(F.count(F.lit(1)).alias("n")).withColumn("name", F.lit("region")).unionByName(table(s, d, "nation").agg(F.count(F.lit(1)).alias("n")).withColumn("name", F.lit("nation"))),
    }
