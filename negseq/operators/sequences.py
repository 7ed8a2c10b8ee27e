"""Sequences from event tables: (sid, pos, item) and sid, len, itemsets."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..plans.planner import small
from ..plans.stage import written

#: Items whose bits share a row of an order.
GROUP = 256


def load(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def build_sequences(df: DataFrame, sid: Column | str, order: list[Column | str], item: Column | str, tie: str = "itemset") -> DataFrame:
    """(sid, pos, item), distinct. tie 'itemset': rows of equal order form one itemset; 'rank': each row is a position of its own. Rows with a null sid, order or item are left out; their positions close up only with tie 'itemset' where no row of that order is left."""
    as_column = lambda c: F.col(c) if isinstance(c, str) else c
    keys = [as_column(c).alias(f"_o{i}") for i, c in enumerate(order)]
    rows = df.select(as_column(sid).cast("long").alias("sid"), as_column(item).cast("string").alias("item"), *keys)
    rows = rows.where(reduce(lambda a, b: a & b, [F.col(c).isNotNull() for c in rows.columns]))
    by = Window.partitionBy("sid").orderBy(*(f"_o{i}" for i in range(len(order))))
    place = F.dense_rank() if tie == "itemset" else F.row_number()
    return rows.select("sid", place.over(by).alias("pos"), "item").distinct()


def lookback(df: DataFrame, sid: str, at: str, outcomes: DataFrame, days: int) -> DataFrame:
    """Events of the days before the outcome event of their sequence. outcomes: sid, outcome_at."""
    joined = df.join(outcomes.select(F.col("sid").alias("_sid"), "outcome_at"), F.col(sid) == F.col("_sid"))
    return joined.where((F.col(at) < F.col("outcome_at")) & (F.col(at) >= F.col("outcome_at") - F.expr(f"interval {int(days)} days"))).drop("_sid", "outcome_at")


def sessions(df: DataFrame, sid: str, at: str, seconds: int) -> DataFrame:
    """Adds session: a new one begins after a pause longer than the given one."""
    by = Window.partitionBy(sid).orderBy(at)
    gap = F.unix_timestamp(F.col(at).cast("timestamp")) - F.unix_timestamp(F.lag(at).over(by).cast("timestamp"))
    return df.withColumn("session", F.sum(F.when(gap > seconds, 1).otherwise(0)).over(by.rowsBetween(Window.unboundedPreceding, 0)))


def nested(items: DataFrame) -> DataFrame:
    """sid, len, itemsets; a missing position is an empty itemset."""
    sets = items.groupBy("sid", "pos").agg(F.array_sort(F.collect_set("item")).alias("items"))
    grouped = sets.groupBy("sid").agg(F.max("pos").alias("len"), F.map_from_entries(F.collect_list(F.struct("pos", "items"))).alias("at"))
    none = F.array().cast("array<string>")
    return grouped.select("sid", "len", F.transform(F.sequence(F.lit(1), F.col("len")), lambda i: F.coalesce(F.element_at("at", i), none)).alias("itemsets"))


def exploded(sequences: DataFrame) -> DataFrame:
    """(sid, pos, item) of nested sequences; null itemsets and items are left out, positions stay."""
    rows = sequences.select("sid", F.posexplode("itemsets").alias("at", "items")).where("items is not null")
    return rows.select("sid", (F.col("at") + 1).alias("pos"), F.explode("items").alias("item")).where("item is not null").distinct()


def first_n(items: DataFrame, n: int) -> DataFrame:
    return items.where(F.col("pos") <= n)


def drop_short(items: DataFrame, least: int) -> DataFrame:
    """Without the sequences of fewer than ``least`` positions. They still count in n(D): count it before and give it to the miner as ``sequences``."""
    length = F.max("pos").over(Window.partitionBy("sid"))
    return items.withColumn("_len", length).where(F.col("_len") >= least).drop("_len")


def last_n(items: DataFrame, n: int) -> DataFrame:
    length = F.max("pos").over(Window.partitionBy("sid"))
    return items.withColumn("_from", length - n).where("pos > _from").select("sid", (F.col("pos") - F.greatest("_from", F.lit(0))).alias("pos"), "item")


def tokenize(text: Column, kind: str) -> Column:
    """Words ([a-z]+ in lower case) or html tags of a whole text."""
    return F.regexp_extract_all(F.lower(text), F.lit("([a-z]+)" if kind == "words" else "<([a-z][a-z0-9]*)"), 1)


def from_tokens(df: DataFrame, sid: str, tokens: Column) -> DataFrame:
    return df.select(F.col(sid).cast("long").alias("sid"), F.posexplode(tokens).alias("at", "item")).select("sid", (F.col("at") + 1).alias("pos"), "item")


# the views on the given tables


def clicks(spark: SparkSession, d: str) -> DataFrame:
    return build_sequences(load(spark, d, "events", "user_id", "ts", "event_id", "event_type"), "user_id", ["ts", "event_id"], "event_type", "rank")


def kinds(spark: SparkSession, d: str) -> DataFrame:
    item = F.concat("event_type", F.lit(":"), F.least(F.floor(F.col("value") / 25), F.lit(3)).cast("string"))
    return build_sequences(load(spark, d, "events", "user_id", "ts", "event_id", "event_type", "value"), "user_id", ["ts", "event_id"], item, "rank")


def days(spark: SparkSession, d: str) -> DataFrame:
    return build_sequences(load(spark, d, "events", "user_id", "ts", "event_type"), "user_id", [F.to_date("ts")], "event_type")


def _day() -> Column:
    """Orders of a customer by date, an itemset a day. The window takes the column that later steps group by, so that these find its partitioning and exchange nothing again."""
    return F.dense_rank().over(Window.partitionBy("sid").orderBy("o_orderdate")).alias("pos")


def _codes(spark: SparkSession, d: str, item: str) -> tuple[DataFrame, DataFrame, int]:
    """Rows (block, codes) with the items of 64 neighbouring part keys as numbers, the items with their numbers, and how many. A row of parts takes a few bytes, so that the table can be shared and no line is exchanged for its part. A key that comes again stands in a further row of its block."""
    part = load(spark, d, "part", "p_partkey", item).toDF("p_partkey", "_item")
    names = part.select(F.col("_item").alias("item")).distinct().select("item", (F.row_number().over(Window.orderBy("item")) - 1).alias("code"))
    n = names.count()
    coded = part.where("p_partkey is not null").join(small(names, n), F.col("_item").eqNullSafe(F.col("item"))).select(F.shiftright("p_partkey", 6).alias("block"), F.expr("p_partkey & 63").cast("int").alias("at"), "code")
    by = Window.partitionBy("block").orderBy("at")
    again = (F.row_number().over(by) - F.rank().over(by)).alias("again")
    placed = F.map_from_entries(F.collect_list(F.struct("at", "code"))).alias("codes")
    blocks = coded.select("block", "at", "code", again).groupBy("block", "again").agg(placed)
    return blocks.select("block", F.transform(F.sequence(F.lit(0), F.lit(63)), lambda i: F.element_at("codes", i)).alias("codes")), names, n


def _baskets(spark: SparkSession, d: str, item: str) -> DataFrame:
    """The items of an order are exchanged and placed as bits, in a row for each GROUP items of the alphabet. The lines find their parts in a shared table, and those of an order meet before they are exchanged, by order alone if one row holds the alphabet, so that the join finds them in place."""
    orders = load(spark, d, "orders", "o_orderkey", "o_custkey", "o_orderdate")
    blocks, names, n = _codes(spark, d, item)
    blocks = written(blocks)
    group = [F.expr(f"cast(code div {GROUP} as int)").alias("group")] if n > GROUP else []
    keys, words = ["group"] if group else [], [f"bits{i}" for i in range(-(-min(max(n, 1), GROUP) // 64))]
    lines = load(spark, d, "lineitem", "l_orderkey", "l_partkey").join(small(blocks, blocks.count()), F.shiftright("l_partkey", 6) == F.col("block"))
    lines = lines.select("l_orderkey", F.get("codes", F.expr("l_partkey & 63").cast("int")).alias("code")).where("code is not null")
    lines = lines.select("l_orderkey", *group, *(F.expr(f"if(code % {GROUP} div 64 = {i}, shiftleft(1L, code % 64), 0L)").alias(x) for i, x in enumerate(words)))
    met = [F.bit_or(x).alias(x) for x in words]
    sets = lines.groupBy("l_orderkey", *keys).agg(*met)
    rows = orders.join(sets, F.col("o_orderkey") == F.col("l_orderkey")).select(F.col("o_custkey").cast("long").alias("sid"), "o_orderdate", *keys, *words)
    placed = rows.select("sid", _day(), *keys, *words).groupBy("sid", "pos", *keys).agg(*met)
    of = names.groupBy(*group).agg(F.transform(F.sort_array(F.collect_list(F.struct("code", "item"))), lambda x: x["item"]).alias("names"))
    placed = placed.join(small(of, n), "group") if group else placed.crossJoin(small(of, 1))
    of_word = lambda i: F.col(words[0]) if len(words) == 1 else F.get(F.array(*words), F.shiftright(i, 6))
    return placed.select("sid", "pos", F.explode(F.filter("names", lambda _, i: F.getbit(of_word(i), i.bitwiseAND(F.lit(63))) == 1)).alias("item"))


def basket_brand(spark: SparkSession, d: str) -> DataFrame:
    return _baskets(spark, d, "p_brand")


def basket_type(spark: SparkSession, d: str) -> DataFrame:
    return _baskets(spark, d, "p_type")


def priority(spark: SparkSession, d: str) -> DataFrame:
    return build_sequences(load(spark, d, "orders", "o_custkey", "o_orderdate", "o_orderpriority"), "o_custkey", ["o_orderdate"], "o_orderpriority")


def turns(spark: SparkSession, d: str) -> DataFrame:
    return load(spark, d, "conversations", "conv_id", "turn", "role").select(F.col("conv_id").alias("sid"), (F.col("turn") + 1).cast("int").alias("pos"), F.col("role").alias("item")).distinct()


def words(spark: SparkSession, d: str) -> DataFrame:
    return from_tokens(load(spark, d, "documents", "doc_id", "text"), "doc_id", tokenize(F.col("text"), "words"))


def tags(spark: SparkSession, d: str) -> DataFrame:
    return from_tokens(load(spark, d, "pages", "page_id", "html"), "page_id", tokenize(F.col("html"), "tags"))


def nation_flow(spark: SparkSession, d: str) -> DataFrame:
    lines = load(spark, d, "lineitem", "l_orderkey", "l_suppkey", "l_shipdate", "l_linenumber")
    buyers = load(spark, d, "customer", "c_custkey", "c_nationkey").join(load(spark, d, "nation", "n_nationkey", "n_regionkey"), F.col("c_nationkey") == F.col("n_nationkey")).join(load(spark, d, "region", "r_regionkey", "r_name"), F.col("n_regionkey") == F.col("r_regionkey"))
    rows = lines.join(load(spark, d, "orders", "o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey")).join(buyers, F.col("o_custkey") == F.col("c_custkey"))
    return build_sequences(rows, "l_suppkey", ["l_shipdate", "l_orderkey", "l_linenumber"], "r_name", "rank")


def status_items(spark: SparkSession, d: str) -> DataFrame:
    orders = load(spark, d, "orders", "o_orderkey", "o_custkey", "o_orderdate")
    rows = orders.join(load(spark, d, "lineitem", "l_orderkey", "l_returnflag", "l_linestatus"), F.col("o_orderkey") == F.col("l_orderkey"))
    rows = rows.select(F.col("o_custkey").cast("long").alias("sid"), "o_orderdate", F.concat("l_returnflag", "l_linestatus").alias("item"))
    return rows.select("sid", _day(), "item").distinct()


def passages(spark: SparkSession, d: str) -> DataFrame:
    return from_tokens(load(spark, d, "benchmark", "item_id", "text"), "item_id", tokenize(F.col("text"), "words"))


def vec_labels(spark: SparkSession, d: str) -> DataFrame:
    rows = load(spark, d, "embeddings", "vec_id", "label")
    return rows.select(F.floor(F.col("vec_id") / 20).cast("long").alias("sid"), (F.col("vec_id") % 20 + 1).cast("int").alias("pos"), F.col("label").cast("string").alias("item")).where("item is not null").distinct()


VIEWS = {f.__name__: f for f in (clicks, kinds, days, basket_brand, basket_type, priority, turns, words, tags, nation_flow, status_items, passages, vec_labels)}
