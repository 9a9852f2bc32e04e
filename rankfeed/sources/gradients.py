"""Matrices per step and worker: ``step, worker, i, j, v``. Missing cells are zero.

The first two are pivots of facts. The others are gradients of small models; at zero parameters (the first step) class probabilities are uniform, so a
gradient is plain arithmetic on counts and SQL can say the same. For later steps ``plans.training`` takes the counts themselves.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import ship

QTR = (25, 50)
QUARTERS = 28  # of the ship dates in the tables
DAY = (24, 5)
EVENTS = ["click", "error", "purchase", "signup", "view"]
LETTERS = 27
LM3 = (LETTERS * LETTERS, LETTERS)
LANGS = ["de", "en", "es", "fr"]
LANG = (LETTERS * LETTERS, len(LANGS))
QUAL = (LETTERS * LETTERS, 2)
EMB = (64, 10)
SEGMENTS = ["AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY"]
STATUSES = ["F", "O", "P"]
PRIORITIES = ["1-URGENT", "2-HIGH", "3-MEDIUM", "4-NOT SPECIFIED", "5-LOW"]
ORD = (len(SEGMENTS) * len(STATUSES) * 12, len(PRIORITIES))
PRICE = (5, 3)
PREFIX = 1500  # characters of a text that make the character model: part of its definition, it is a training workload and no filter of documents


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return ship(spark).read.parquet(f"{sf_dir}/{name}.parquet")


def index_in(values: list[str], column: str) -> Column:
    return (F.array_position(F.array(*map(F.lit, values)), F.col(column)) - 1).cast("int")


def worker_of(key: str, workers: int) -> Column:
    return F.pmod(F.col(key), F.lit(workers)).cast("int")


def quarterly(spark: SparkSession, sf_dir: str, workers: int = 4) -> DataFrame:
    """Shipped quantity by supplier nation and part size; one step per quarter."""
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey", "l_quantity", "l_shipdate")
    suppliers = table(spark, sf_dir, "supplier").select(F.col("s_suppkey").alias("l_suppkey"), F.col("s_nationkey").alias("i"))
    parts = table(spark, sf_dir, "part").select(F.col("p_partkey").alias("l_partkey"), (F.col("p_size") - 1).alias("j"))
    step = (F.year("l_shipdate") - 1995) * 4 + F.quarter("l_shipdate") - 1
    joined = lines.join(suppliers, "l_suppkey").join(parts, "l_partkey")
    return joined.groupBy(step.alias("step"), worker_of("l_orderkey", workers).alias("worker"), "i", "j").agg(F.sum("l_quantity").alias("v"))


def quarters(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``step, samples``: the lines shipped in each quarter."""
    step = (F.year("l_shipdate") - 1995) * 4 + F.quarter("l_shipdate") - 1
    return table(spark, sf_dir, "lineitem").where("l_shipdate is not null").groupBy(step.alias("step")).agg(F.count(F.lit(1)).alias("samples"))


def order_weeks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``epoch``: the weeks with orders, counted from the first order."""
    days = table(spark, sf_dir, "orders").where("o_orderdate is not null").select(F.to_date("o_orderdate").alias("day")).distinct()
    first = days.agg(F.min("day").alias("first"))
    return days.join(F.broadcast(first)).select(F.floor(F.datediff("day", "first") / 7).cast("int").alias("epoch")).distinct()


def tensor_shapes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``param, shape``: for each return flag a tensor of suppliers, line numbers and quantities, for each line status a vector over parts."""
    lines = table(spark, sf_dir, "lineitem")
    size = lambda c: F.count_distinct(c).cast("int")
    tensors = lines.groupBy(F.concat(F.lit("flag "), "l_returnflag").alias("param")).agg(size("l_suppkey").alias("a"), size("l_linenumber").alias("b"), size("l_quantity").alias("c"))
    vectors = lines.groupBy(F.concat(F.lit("status "), "l_linestatus").alias("param")).agg(size("l_partkey").alias("a"))
    return tensors.select("param", F.array("a", "b", "c").alias("shape")).unionByName(vectors.select("param", F.array("a").alias("shape")))


def day_cells(events: DataFrame, step: Column, workers: int) -> DataFrame:
    cents = F.round(F.col("value") * 100).cast("bigint")
    known = events.where(F.col("event_type").isin(EVENTS))
    return known.groupBy(step.alias("step"), worker_of("event_id", workers).alias("worker"), F.hour("ts").alias("i"), index_in(EVENTS, "event_type").alias("j")).agg(F.sum(cents).cast("double").alias("v"))


def daily(spark: SparkSession, sf_dir: str, workers: int = 4) -> DataFrame:
    """Value in cents by hour and kind of event; one step per day."""
    return day_cells(table(spark, sf_dir, "events"), F.datediff(F.to_date("ts"), F.lit("2024-01-01").cast("date")), workers)


def code(k) -> Column:
    return F.greatest(F.ascii(F.element_at("letters", k)) - 96, F.lit(0))


def characters(texts: DataFrame, text: Column) -> DataFrame:
    """``letters`` of the first characters of each text, all but a-z replaced by one sign before a."""
    plain = F.regexp_replace(F.substring(F.lower(text), 1, PREFIX), "[^a-z]", "`")
    return texts.withColumn("letters", F.filter(F.split(plain, ""), lambda x: x != "")).where(F.size("letters") >= 2)


def chains(texts: DataFrame, length: int) -> DataFrame:
    """One row per run of ``length`` letters, ``codes`` its numbers 0..26; other columns stay."""
    at = F.explode(F.sequence(F.lit(1), F.size("letters") - (length - 1)))
    several = texts.where(F.size("letters") >= length).withColumn("at", at)
    return several.select(*[c for c in texts.columns if c != "letters"], F.array(*[code(F.col("at") + k) for k in range(length)]).alias("codes"))


def trigram_counts(texts: DataFrame, key: str, text: Column, workers: int) -> DataFrame:
    """``fold, worker, i, j, n``: how often letter j follows the two letters of i; fold is the key modulo 10. Bounded by the model, whatever the input."""
    rows = chains(characters(texts.where(F.col(key).isNotNull()), text).select(key, "letters"), 3)
    return rows.groupBy(F.pmod(F.col(key), F.lit(10)).cast("int").alias("fold"), worker_of(key, workers).alias("worker"), (F.col("codes")[0] * LETTERS + F.col("codes")[1]).alias("i"), F.col("codes")[2].alias("j")).agg(F.count(F.lit(1)).alias("n"))


def softmax_start(counts: DataFrame, classes: int, scale: float) -> DataFrame:
    """Gradient at zero parameters of ``worker, i, j, n``: (row total / classes - count) * scale / worker total, as step 0."""
    rows = counts.groupBy("worker", "i").agg(F.sum("n").alias("row"))
    totals = counts.groupBy("worker").agg(F.sum("n").alias("total"))
    dense = rows.withColumn("j", F.explode(F.sequence(F.lit(0), F.lit(classes - 1)))).join(counts, ["worker", "i", "j"], "left").join(totals, "worker")
    return dense.select(F.lit(0).alias("step"), "worker", "i", "j", ((F.col("row") / classes - F.coalesce("n", F.lit(0))) * scale / F.col("total")).alias("v"))


def merged_folds(counts: DataFrame, folds: list[int]) -> DataFrame:
    return counts.where(F.col("fold").isin(folds)).groupBy("worker", "i", "j").agg(F.sum("n").alias("n"))


TRAIN = [f for f in range(10) if f not in (0, 5)]  # fold 0 tests, fold 5 validates


def letters_model(spark: SparkSession, sf_dir: str, workers: int = 4) -> DataFrame:
    """Next letter from the two before it, over documents."""
    counts = trigram_counts(table(spark, sf_dir, "documents").select("doc_id", "text"), "doc_id", F.col("text"), workers)
    return softmax_start(merged_folds(counts, TRAIN), LETTERS, LETTERS)


def pages_model(spark: SparkSession, sf_dir: str, workers: int = 4) -> DataFrame:
    """The same model over pages without their tags."""
    counts = trigram_counts(table(spark, sf_dir, "pages").select("page_id", "html"), "page_id", F.regexp_replace("html", "<[^>]*>", " "), workers)
    return softmax_start(merged_folds(counts, TRAIN), LETTERS, LETTERS)


def bigram_counts(spark: SparkSession, sf_dir: str, classes: DataFrame, workers: int) -> DataFrame:
    """``fold, worker, i, j, n``: pairs of letters i in texts of class j; ``classes`` has ``doc_id, j``."""
    texts = table(spark, sf_dir, "documents").select("doc_id", "text").join(classes, "doc_id")
    rows = chains(characters(texts, F.col("text")).select("doc_id", "j", "letters"), 2)
    return rows.groupBy(F.pmod(F.col("doc_id"), F.lit(10)).cast("int").alias("fold"), worker_of("doc_id", workers).alias("worker"), (F.col("codes")[0] * LETTERS + F.col("codes")[1]).alias("i"), "j").agg(F.count(F.lit(1)).alias("n"))


def languages_model(spark: SparkSession, sf_dir: str, workers: int = 4) -> DataFrame:
    """Language from pairs of letters, each pair a sample."""
    classes = table(spark, sf_dir, "documents").where(F.col("lang").isin(LANGS)).select("doc_id", index_in(LANGS, "lang").alias("j"))
    return softmax_start(merged_folds(bigram_counts(spark, sf_dir, classes, workers), TRAIN), len(LANGS), 1.0)


def quality_model(spark: SparkSession, sf_dir: str, workers: int = 4, target: str = "quality") -> DataFrame:
    """A label from pairs of letters."""
    classes = table(spark, sf_dir, "labels").where(F.col(target).isNotNull()).select("doc_id", F.col(target).cast("int").alias("j"))
    return softmax_start(merged_folds(bigram_counts(spark, sf_dir, classes, workers), TRAIN), 2, 1.0)


def orders_counts(spark: SparkSession, sf_dir: str, workers: int = 4) -> DataFrame:
    customers = table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("o_custkey"), index_in(SEGMENTS, "c_mktsegment").alias("segment"))
    o = table(spark, sf_dir, "orders").join(customers, "o_custkey")
    cell = (F.col("segment") * len(STATUSES) + index_in(STATUSES, "o_orderstatus")) * 12 + F.month("o_orderdate") - 1
    return o.groupBy(worker_of("o_orderkey", workers).alias("worker"), cell.cast("int").alias("i"), index_in(PRIORITIES, "o_orderpriority").alias("j")).agg(F.count(F.lit(1)).alias("n"))


def orders_model(spark: SparkSession, sf_dir: str, workers: int = 4) -> DataFrame:
    """Priority of an order from segment, status and month."""
    return softmax_start(orders_counts(spark, sf_dir, workers).where("i is not null and j is not null"), len(PRIORITIES), 1.0)


def embeddings_model(spark: SparkSession, sf_dir: str, workers: int = 4) -> DataFrame:
    """Softmax regression of the label on the vector: mean over a worker's rows of x (p - 1[label]), p uniform at zero parameters."""
    e = table(spark, sf_dir, "embeddings").select(worker_of("vec_id", workers).alias("worker"), "label", F.posexplode("embedding").alias("i", "x"))
    x = F.col("x").cast("double")
    by_label = e.groupBy("worker", "i", F.col("label").alias("j")).agg(F.sum(x).alias("s"))
    sizes = table(spark, sf_dir, "embeddings").groupBy(worker_of("vec_id", workers).alias("worker")).agg(F.count(F.lit(1)).alias("rows"))
    whole = by_label.groupBy("worker", "i").agg(F.sum("s").alias("whole"))
    dense = whole.withColumn("j", F.explode(F.sequence(F.lit(0), F.lit(EMB[1] - 1)))).join(by_label, ["worker", "i", "j"], "left").join(sizes, "worker")
    return dense.select(F.lit(0).alias("step"), "worker", "i", "j", ((F.col("whole") / EMB[1] - F.coalesce("s", F.lit(0.0))) / F.col("rows")).alias("v"))


def embeddings_bias(spark: SparkSession, sf_dir: str, workers: int = 4) -> DataFrame:
    """``step, worker, i, v``: gradient of the bias of the same model, a vector that travels uncompressed."""
    n = table(spark, sf_dir, "embeddings").groupBy(worker_of("vec_id", workers).alias("worker"), F.col("label").alias("i")).agg(F.count(F.lit(1)).alias("n"))
    sizes = n.groupBy("worker").agg(F.sum("n").alias("rows"))
    dense = sizes.withColumn("i", F.explode(F.sequence(F.lit(0), F.lit(EMB[1] - 1)))).join(n, ["worker", "i"], "left")
    return dense.select(F.lit(0).alias("step"), "worker", "i", (F.lit(1.0) / EMB[1] - F.coalesce("n", F.lit(0)) / F.col("rows")).alias("v"))


def prices_model(spark: SparkSession, sf_dir: str, workers: int = 4) -> DataFrame:
    """Least squares of list, discounted and taxed price (thousands) on quantity, discount, tax and two flags, at zero parameters: -mean(x y)."""
    features = [F.col("l_quantity") / 50, F.col("l_discount") + 0.0, F.col("l_tax") + 0.0, (F.col("l_returnflag") == "R").cast("double"), (F.col("l_linestatus") == "O").cast("double")]
    price = F.col("l_extendedprice") / 1000
    targets = [price, price * (1 - F.col("l_discount")), price * (1 - F.col("l_discount")) * (1 + F.col("l_tax"))]
    lines = table(spark, sf_dir, "lineitem").withColumn("worker", worker_of("l_orderkey", workers))
    sums = lines.groupBy("worker").agg(F.count(F.lit(1)).alias("rows"), *[F.sum(x * y).alias(f"s{i}_{j}") for i, x in enumerate(features) for j, y in enumerate(targets)])
    cells = F.explode(F.array(*[F.struct(F.lit(i).alias("i"), F.lit(j).alias("j"), F.col(f"s{i}_{j}").alias("s")) for i in range(PRICE[0]) for j in range(PRICE[1])])).alias("c")
    return sums.select("worker", "rows", cells).select(F.lit(0).alias("step"), "worker", "c.i", "c.j", (-F.col("c.s") / F.col("rows")).alias("v"))


def hashed_words_counts(spark: SparkSession, sf_dir: str, side: int = 2048, workers: int = 4) -> DataFrame:
    """``fold, worker, i, j, n``: next word by word, both hashed to ``side`` buckets; near-square and large, for high ratios."""
    bucket = lambda k: F.pmod(F.conv(F.substring(F.md5(F.element_at("words", k)), 1, 8), 16, 10).cast("bigint"), F.lit(side)).cast("int")
    words = table(spark, sf_dir, "documents").select("doc_id", F.filter(F.split(F.lower("text"), r"[^\p{L}]+"), lambda w: w != "").alias("words")).where(F.size("words") > 1)
    pairs = words.withColumn("at", F.explode(F.sequence(F.lit(1), F.size("words") - 1))).select("doc_id", bucket(F.col("at")).alias("i"), bucket(F.col("at") + 1).alias("j"))
    return pairs.groupBy(F.pmod(F.col("doc_id"), F.lit(10)).cast("int").alias("fold"), worker_of("doc_id", workers).alias("worker"), "i", "j").agg(F.count(F.lit(1)).alias("n"))
