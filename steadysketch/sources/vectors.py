"""Input vectors (query_id, key, value) from the given tables, and the same as SQL text."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.hashing import PRIME, coefficients, key_from_string, poly_hash, sql_key, sql_poly
from ..plans.physical import by_query, spread


def read_table(spark: SparkSession, sf_dir: str, name: str, columns: list[str] | None = None, where: str | None = None) -> DataFrame:
    """A table with its columns and filter pushed to the scan; event times become zoned timestamps."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    if where:
        df = df.where(where)
    if columns:
        df = df.select(*columns)
    for field in df.schema:
        if field.dataType.typeName() == "timestamp_ntz":
            df = df.withColumn(field.name, F.col(field.name).cast("timestamp"))
    return df


def vector_from(df: DataFrame, key: Column, value: Column, query: Column | None = None) -> DataFrame:
    """Sums of ``value`` by key within each query; nulls of either are dropped, as are zero sums."""
    if query is None:
        # Without a constant among the grouping keys the rows stay partitioned by key, and what is grouped by key later needs no shuffle.
        rows = df.select(key.cast("bigint").alias("key"), value.alias("value")).where("key is not null and value is not null")
        summed = rows.groupBy("key").agg(F.sum("value").alias("value")).where("value <> 0")
        return summed.select(F.lit(0).cast("bigint").alias("query_id"), "key", "value")
    rows = df.select(query.cast("bigint").alias("query_id"), key.cast("bigint").alias("key"), value.alias("value"))
    rows = rows.where("key is not null and value is not null and query_id is not null")
    return rows.groupBy("query_id", "key").agg(F.sum("value").alias("value")).where("value <> 0")


def tokens_of(df: DataFrame, text: str = "text") -> DataFrame:
    """Adds a row per lower-cased token between spaces and line ends."""
    return spread(df).withColumn("token", F.explode(F.split(F.regexp_replace(F.lower(F.col(text)), "\n", " "), " "))).where("token <> ''")


def doc_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents", ["text"])
    return vector_from(tokens_of(docs), key_from_string(F.col("token")), F.lit(1).cast("bigint"))


def conversation_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    return vector_from(tokens_of(read_table(spark, sf_dir, "conversations", ["text"])), key_from_string(F.col("token")), F.lit(1).cast("bigint"))


def source_contrast(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Tokens of three sources count +1, of the others -1."""
    docs = read_table(spark, sf_dir, "documents", ["text", "source"])
    sign = F.when(F.col("source").isin("src0", "src1", "src2"), 1).otherwise(-1).cast("bigint")
    return vector_from(tokens_of(docs), key_from_string(F.col("token")), sign)


def html_tags(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = read_table(spark, sf_dir, "pages", ["html"])
    tags = pages.select(F.explode(F.regexp_extract_all("html", F.lit(r"<([a-z][a-z0-9]*)"), F.lit(1))).alias("tag"))
    return vector_from(tags, key_from_string(F.col("tag")), F.lit(1).cast("bigint"))


def url_hosts(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = read_table(spark, sf_dir, "pages", ["url"])
    host = F.regexp_extract("url", r"^[a-z]+://([^/]+)", 1)
    return vector_from(pages.where(host != ""), key_from_string(host), F.lit(1).cast("bigint"))


def cents(column: str) -> Column:
    return F.round(F.col(column) * 100).cast("bigint")


def user_values(spark: SparkSession, sf_dir: str) -> DataFrame:
    return vector_from(read_table(spark, sf_dir, "events", ["user_id", "value"]), F.col("user_id"), cents("value"))


def part_quantities(spark: SparkSession, sf_dir: str) -> DataFrame:
    return vector_from(read_table(spark, sf_dir, "lineitem", ["l_partkey", "l_quantity"]), F.col("l_partkey"), F.col("l_quantity").cast("bigint"))


def skewed_key(part: Column) -> Column:
    m = part % 1000
    return F.floor((m * m * m * m) / F.lit(500_000_000)).cast("bigint")


def skewed_parts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Part quantities with keys drawn together by the fourth power, in integers: a controlled skew."""
    return vector_from(read_table(spark, sf_dir, "lineitem", ["l_partkey", "l_quantity"]), skewed_key(F.col("l_partkey")), F.col("l_quantity").cast("bigint"))


def embedding_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A query for each vector: its components in ten-thousandths."""
    vectors = by_query(read_table(spark, sf_dir, "embeddings", ["vec_id", "embedding"]), "vec_id")
    rows = vectors.select("vec_id", F.posexplode("embedding").alias("key", "x"))
    return vector_from(rows, F.col("key"), F.round(F.col("x").cast("double") * 10000).cast("bigint"), F.col("vec_id"))


def class_sums(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = read_table(spark, sf_dir, "embeddings", ["label", "embedding"]).select("label", F.posexplode("embedding").alias("key", "x"))
    return vector_from(rows, F.col("key"), F.round(F.col("x").cast("double") * 10000).cast("bigint"), F.col("label"))


def hourly_users(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A query for each hour since 2024-01-01: value by user."""
    events = read_table(spark, sf_dir, "events", ["ts", "user_id", "value"])
    hour = F.floor((F.unix_timestamp("ts") - 1704067200) / 3600)
    return vector_from(events, F.col("user_id"), cents("value"), hour)


def net_users(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Purchases and sign-ups add, everything else takes two thirds away."""
    events = read_table(spark, sf_dir, "events", ["event_type", "user_id", "value"])
    value = F.when(F.col("event_type").isin("purchase", "signup"), cents("value")).otherwise(-F.floor(cents("value") * 66 / 100))
    return vector_from(events, F.col("user_id"), value.cast("bigint"))


def plant(vec: DataFrame, key: int, weight: Column | int) -> DataFrame:
    """Adds ``weight`` at one key to every query."""
    more = vec.select("query_id").distinct().select("query_id", F.lit(key).cast("bigint").alias("key"), F.lit(weight).cast("bigint").alias("value"))
    return vec.select("query_id", "key", "value").unionAll(more).groupBy("query_id", "key").agg(F.sum("value").alias("value"))


# -- tails ----------------------------------------------------------------------------------------
def gaussian(key: Column, seed: int, scale: int = 1000) -> Column:
    """A rounded normal deviate of a key: twelve hashed uniforms of two bytes each, summed in integers."""
    total = None
    for j in range(4):
        h = poly_hash(key, [F.lit(c[0]).cast("bigint") for c in coefficients(seed, 10 + j, 1, 3)])
        for shift in (1, 1024, 1024 * 1024):
            part = F.floor(h / shift) % 1024
            total = part if total is None else total + part
    # The sum of twelve uniforms on 0..1023 has mean 6138 and deviation 1024.
    return F.floor(((total - 6138) * scale) / 1024).cast("bigint")


def sql_gaussian(key: str, seed: int, scale: int = 1000) -> str:
    parts = []
    for j in range(4):
        h = sql_poly(key, coefficients(seed, 10 + j, 1, 3), "0")
        parts += [f"((({h}) // {shift}) % 1024)" for shift in (1, 1024, 1024 * 1024)]
    return f"CAST(floor(((({' + '.join(parts)}) - 6138) * {scale}) / 1024) AS BIGINT)"


def tails(spark: SparkSession, sf_dir: str, m: int, count: int, seed: int = 5, kind: str = "gaussian") -> DataFrame:
    """(tail_id, key, value): disjoint blocks of m order keys, with hashed values; keys repeat in no tail.

    The universe is extended by replicas of the order keys when ``m * count`` needs more than there are.
    """
    orders = read_table(spark, sf_dir, "orders", ["o_orderkey"])
    n, top = orders.agg(F.count("*"), F.max("o_orderkey")).first()
    copies = -(-m * count // n)
    base = orders.withColumn("replica", F.explode(F.sequence(F.lit(0), F.lit(copies - 1))))
    keyed = base.select((F.col("o_orderkey") * copies + F.col("replica")).cast("bigint").alias("key"))
    if (top + 1) * copies >= PRIME:
        raise ValueError("the keys of the tails outgrow the hash field")
    blocks = keyed.where(F.col("key") < m * count).withColumn("tail_id", F.floor(F.col("key") / m).cast("bigint"))
    sign = 1 - 2 * (poly_hash(F.col("key"), [F.lit(c[0]).cast("bigint") for c in coefficients(seed, 9, 1, 3)]) % 2)
    value = gaussian(F.col("key"), seed) if kind == "gaussian" else sign.cast("bigint")
    return blocks.select("tail_id", "key", value.alias("value")).where("value <> 0")


def sql_tails(m: int, count: int, seed: int = 5) -> str:
    """The same tails as SQL."""
    copies = f"(SELECT CAST(ceil({m * count} / count(*)) AS BIGINT) FROM orders)"
    keys = f"SELECT CAST(o_orderkey * {copies} + r AS BIGINT) AS key FROM orders, (SELECT unnest(range(0, {copies})) AS r)"
    valued = f"SELECT key // {m} AS tail_id, key, {sql_gaussian('key', seed)} AS value FROM ({keys}) WHERE key < {m * count}"
    return f"SELECT tail_id, key, value FROM ({valued}) WHERE value <> 0"


# -- SQL of the vectors ---------------------------------------------------------------------------
def _sums(inner: str) -> str:
    return f"SELECT CAST(query_id AS BIGINT) AS query_id, CAST(key AS BIGINT) AS key, CAST(sum(value) AS BIGINT) AS value FROM ({inner}) GROUP BY ALL HAVING sum(value) <> 0"


_TOKENS = "SELECT {extra} unnest(string_split(replace(lower(text), chr(10), ' '), ' ')) AS token FROM {table}"

SQL = {
    "doc_tokens": _sums(f"SELECT 0 AS query_id, {sql_key('token')} AS key, 1 AS value FROM ({_TOKENS.format(extra='', table='documents')}) WHERE token <> ''"),
    "conversation_tokens": _sums(f"SELECT 0 AS query_id, {sql_key('token')} AS key, 1 AS value FROM ({_TOKENS.format(extra='', table='conversations')}) WHERE token <> ''"),
    "source_contrast": _sums(f"SELECT 0 AS query_id, {sql_key('token')} AS key, CASE WHEN source IN ('src0', 'src1', 'src2') THEN 1 ELSE -1 END AS value FROM ({_TOKENS.format(extra='source,', table='documents')}) WHERE token <> ''"),
    "html_tags": _sums(f"SELECT 0 AS query_id, {sql_key('tag')} AS key, 1 AS value FROM (SELECT unnest(regexp_extract_all(html, '<([a-z][a-z0-9]*)', 1)) AS tag FROM pages)"),
    "url_hosts": _sums(f"SELECT 0 AS query_id, {sql_key('host')} AS key, 1 AS value FROM (SELECT regexp_extract(url, '^[a-z]+://([^/]+)', 1) AS host FROM pages) WHERE host <> ''"),
    "user_values": _sums("SELECT 0 AS query_id, user_id AS key, CAST(round(value * 100) AS BIGINT) AS value FROM events WHERE value IS NOT NULL"),
    "part_quantities": _sums("SELECT 0 AS query_id, l_partkey AS key, CAST(l_quantity AS BIGINT) AS value FROM lineitem"),
    "skewed_parts": _sums("SELECT 0 AS query_id, ((l_partkey % 1000) * (l_partkey % 1000) * (l_partkey % 1000) * (l_partkey % 1000)) // 500000000 AS key, CAST(l_quantity AS BIGINT) AS value FROM lineitem"),
    "embedding_rows": _sums("SELECT vec_id AS query_id, generate_subscripts(embedding, 1) - 1 AS key, CAST(round(CAST(unnest(embedding) AS DOUBLE) * 10000) AS BIGINT) AS value FROM embeddings"),
    "class_sums": _sums("SELECT label AS query_id, generate_subscripts(embedding, 1) - 1 AS key, CAST(round(CAST(unnest(embedding) AS DOUBLE) * 10000) AS BIGINT) AS value FROM embeddings"),
    "hourly_users": _sums("SELECT floor((epoch(ts) - 1704067200) / 3600) AS query_id, user_id AS key, CAST(round(value * 100) AS BIGINT) AS value FROM events WHERE value IS NOT NULL"),
    "net_users": _sums("SELECT 0 AS query_id, user_id AS key, CASE WHEN event_type IN ('purchase', 'signup') THEN CAST(round(value * 100) AS BIGINT) ELSE -CAST(floor(CAST(round(value * 100) AS BIGINT) * 66 / 100) AS BIGINT) END AS value FROM events WHERE value IS NOT NULL"),
}

VECTORS = {f.__name__: f for f in (doc_tokens, conversation_tokens, source_contrast, html_tags, url_hosts, user_values, part_quantities, skewed_parts, embedding_rows, class_sums, hourly_users, net_users)}
