"""Tables as event streams: readers, adapters to (stream_key, sym, t, eid), writers and views."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")
EVENTS = T.StructType([T.StructField("stream_key", T.StringType()), T.StructField("sym", T.StringType()), T.StructField("t", T.LongType()), T.StructField("eid", T.LongType())])
SECOND = 1_000_000


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def register_views(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = TABLES) -> None:
    """A temporary view for each table, for users of SQL."""
    for n in names:
        read_table(spark, sf_dir, n).createOrReplaceTempView(n)


def micros(c: str | Column) -> Column:
    """Microseconds of a time; the session is in UTC, where a time without zone keeps its value."""
    return F.unix_micros((F.col(c) if isinstance(c, str) else c).cast("timestamp"))


def as_events(df: DataFrame, sym: Column | str, t: Column | str, eid: Column | str | None = None, stream_key: Column | str | None = None, on_null: str = "drop", tie_order: str = "position") -> DataFrame:
    """Any table as events. tie_order "time" sets eid to 0: then only times tell events apart, whatever their order.

    Rows with a null symbol or time are dropped, or with on_null "fail" stop the query.
    """
    if on_null not in ("drop", "fail") or tie_order not in ("position", "time"):
        raise ValueError("on_null is drop or fail; tie_order is position or time")
    if tie_order == "position" and eid is None:
        raise ValueError("tie_order position needs an eid that is unique in each stream")
    as_col = lambda c: F.col(c) if isinstance(c, str) else c
    key = F.lit("all") if stream_key is None else F.coalesce(as_col(stream_key).cast("string"), F.lit(""))
    out = df.select(key.alias("stream_key"), as_col(sym).cast("string").alias("sym"), as_col(t).cast("bigint").alias("t"), (F.lit(0) if tie_order == "time" else as_col(eid)).cast("bigint").alias("eid"))
    if on_null == "drop":
        return out.filter(F.col("sym").isNotNull() & F.col("t").isNotNull())
    return out.select("stream_key", F.coalesce("sym", F.raise_error(F.lit("null symbol"))).alias("sym"), F.coalesce("t", F.raise_error(F.lit("null time")).cast("bigint")).alias("t"), "eid")


def read_events(spark: SparkSession, path: str, format: str = "parquet", schema: T.StructType = EVENTS, **options: str) -> DataFrame:
    """Recordings in any of Spark's formats; the schema is given, never inferred."""
    return spark.read.format(format).schema(schema).options(**options).load(path).select(*schema.fieldNames())


def write_events(ev: DataFrame, path: str, width: int, mode: str = "errorifexists") -> None:
    """A store partitioned by time segment and sorted by symbol and time inside, so that symbol filters prune row groups."""
    seg = F.floor(F.col("t") / width).cast("bigint")
    ev.withColumn("seg", seg).repartition("seg", "stream_key").sortWithinPartitions("seg", "sym", "t", "eid").write.mode(mode).partitionBy("seg").parquet(path)


def write_frequent(frequent: DataFrame, path: str, format: str = "parquet", mode: str = "overwrite") -> None:
    frequent.write.format(format).mode(mode).save(path)


def read_event_stream(spark: SparkSession, path: str, schema: T.StructType = EVENTS, files_a_batch: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_a_batch).parquet(path)


def rate_events(spark: SparkSession, rows_a_second: int, symbols: int = 26) -> DataFrame:
    """An endless demo stream: symbols by a hash of the row's number."""
    raw = spark.readStream.format("rate").option("rowsPerSecond", rows_a_second).load()
    return raw.select(F.lit("all").alias("stream_key"), F.concat(F.lit("u"), F.pmod(F.xxhash64("value"), F.lit(symbols))).alias("sym"), F.unix_micros("timestamp").alias("t"), F.col("value").alias("eid"))


# the given tables as streams


def stable_sample(df: DataFrame, key: str, share: float) -> DataFrame:
    """About `share` of the rows by a hash of their key: the same rows on any partitioning, in any engine with MD5."""
    draw = F.conv(F.substring(F.md5(F.col(key).cast("string")), 1, 6), 16, 10).cast("bigint")
    return df.filter(draw < share * 16_777_216)


def event_types(spark: SparkSession, sf_dir: str, by_user: bool = False) -> DataFrame:
    df = read_table(spark, sf_dir, "events")
    return as_events(df, "event_type", micros("ts"), "event_id", "user_id" if by_user else None)


def user_symbols(spark: SparkSession, sf_dir: str, symbols: int = 26) -> DataFrame:
    df = read_table(spark, sf_dir, "events")
    return as_events(df, F.concat(F.lit("u"), F.col("user_id") % symbols), micros("ts"), "event_id")


def day_slices(spark: SparkSession, sf_dir: str, symbols: int = 60, days: int = 10) -> DataFrame:
    """Three recordings of ten days each as streams 0, 1 and 2."""
    df = read_table(spark, sf_dir, "events")
    part = F.floor((F.dayofmonth("ts") - 1) / days).cast("int")
    return as_events(df, F.concat(F.lit("u"), F.col("user_id") % symbols), micros("ts"), "event_id", part)


def json_symbols(spark: SparkSession, sf_dir: str, symbols: int = 26) -> DataFrame:
    df = read_table(spark, sf_dir, "events")
    return as_events(df, F.concat(F.lit("k"), F.get_json_object("props", "$.k").cast("int") % symbols), micros("ts"), "event_id")


def value_symbols(spark: SparkSession, sf_dir: str, width: float = 50.0) -> DataFrame:
    df = read_table(spark, sf_dir, "events")
    return as_events(df, F.concat_ws(":", "event_type", F.least(F.lit(3), F.floor(F.col("value") / width)).cast("string")), micros("ts"), "event_id")


def order_priorities(spark: SparkSession, sf_dir: str) -> DataFrame:
    return as_events(read_table(spark, sf_dir, "orders"), "o_orderpriority", micros("o_orderdate"), "o_orderkey", "o_custkey")


def supplier_flags(spark: SparkSession, sf_dir: str) -> DataFrame:
    """lineitem has no trustworthy order among rows of one day, so times alone tell its events apart."""
    return as_events(read_table(spark, sf_dir, "lineitem"), F.concat("l_returnflag", "l_linestatus"), micros("l_shipdate"), None, "l_suppkey", tie_order="time")


def supplier_brands(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = read_table(spark, sf_dir, "lineitem").select("l_partkey", "l_suppkey", "l_shipdate")
    part = read_table(spark, sf_dir, "part").select("p_partkey", "p_brand")
    return as_events(lines.join(part, lines["l_partkey"] == part["p_partkey"]), "p_brand", micros("l_shipdate"), None, "l_suppkey", tie_order="time")


def region_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    orders = read_table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderdate")
    customer = read_table(spark, sf_dir, "customer").select("c_custkey", "c_nationkey")
    nation = read_table(spark, sf_dir, "nation").select("n_nationkey", "n_regionkey")
    region = read_table(spark, sf_dir, "region").select("r_regionkey", "r_name")
    star = orders.join(customer, orders["o_custkey"] == customer["c_custkey"]).join(nation, F.col("c_nationkey") == F.col("n_nationkey")).join(region, F.col("n_regionkey") == F.col("r_regionkey"))
    return as_events(star, "r_name", micros("o_orderdate"), "o_orderkey")


def conversation_roles(spark: SparkSession, sf_dir: str) -> DataFrame:
    return as_events(read_table(spark, sf_dir, "conversations"), "role", F.col("turn") * SECOND, "turn", "conv_id")


def document_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Lower-cased words of letters, in order, one second apart."""
    words = read_table(spark, sf_dir, "documents").select("doc_id", F.posexplode(F.regexp_extract_all(F.lower("text"), F.lit("[a-z]+"), F.lit(0))).alias("i", "word"))
    return as_events(words, "word", F.col("i").cast("bigint") * SECOND, "i", "doc_id")


def page_tags(spark: SparkSession, sf_dir: str) -> DataFrame:
    tags = read_table(spark, sf_dir, "pages").select("page_id", F.posexplode(F.regexp_extract_all("html", F.lit("<([a-z][a-z0-9]*)"), F.lit(1))).alias("i", "tag"))
    return as_events(tags, "tag", F.col("i").cast("bigint") * SECOND, "i", "page_id")


def embedding_labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    return as_events(read_table(spark, sf_dir, "embeddings"), F.concat(F.lit("l"), "label"), F.col("vec_id") * SECOND, "vec_id")
