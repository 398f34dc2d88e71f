"""Reports joined to other tables, changes over time, windows and streams."""

from __future__ import annotations


from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.sqlsurface import register
from ..operators import estimators as E
from ..operators import metrics as M
from ..operators import sketch as S
from ..operators.sizing import TAU_A, TAU_B
from ..runtime import scratch_path
from ..sources import vectors as V
from ..streaming.continuous import RunningSketch, session_vectors, windowed_cells
from . import sqltext as T
from .base import MID, PARTS, SMALL, USERS, query
from .sketches import HOURLY, agreed, agreed_sql, hourly_agreement


@query(
    T.with_(
        *agreed_sql(T.vector("skewed_parts"), PARTS, 129), ("report", T.threshold("agreed", MID)),
        then="SELECT r.key, r.sign, p.p_name AS name, p.p_brand AS brand FROM report r LEFT JOIN part p ON r.key = p.p_partkey",
    )
)
def report_with_part_names(spark: SparkSession, sf_dir: str) -> DataFrame:
    report = E.threshold_report(agreed(V.skewed_parts(spark, sf_dir), PARTS), MID)
    parts = V.read_table(spark, sf_dir, "part", ["p_partkey", "p_name", "p_brand"])
    return report.join(parts, F.col("key") == F.col("p_partkey"), "left").select("key", "sign", F.col("p_name").alias("name"), F.col("p_brand").alias("brand"))


_INSIDE = f"SELECT query_id, key, greatest(p_plus, p_minus) >= {MID!r} AS inside FROM agreed"


@query(T.with_(*HOURLY, ("said", _INSIDE), ("last", "SELECT key, arg_max(inside, query_id) AS inside, max(query_id) AS hour FROM said WHERE query_id <= 359 GROUP BY ALL"), then="SELECT key, hour FROM last WHERE inside"))
def report_as_of(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Users reported in their last hour up to the middle of the month."""
    rows = hourly_agreement(spark, sf_dir)[1].where("query_id <= 359")
    inside = F.greatest("p_plus", "p_minus") >= MID
    last = rows.groupBy("key").agg(F.max_by(inside, "query_id").alias("inside"), F.max("query_id").alias("hour"))
    return last.where("inside").select("key", "hour")


@query(
    T.with_(
        *HOURLY, ("said", _INSIDE), ("r", "SELECT query_id, key FROM said WHERE inside"), ("o", "SELECT o_orderkey AS order_key, o_custkey AS key, o_orderkey % 720 AS hour FROM orders WHERE o_custkey IN (SELECT key FROM vec)"),
        then="SELECT order_key, key, hour, (SELECT max(r.query_id) FROM r WHERE r.key = o.key AND r.query_id <= o.hour) AS reported_at FROM o",
    )
)
def report_asof_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    """For each order of a user, the last hour up to the order's in which the user was reported."""
    vec, rows = hourly_agreement(spark, sf_dir)
    reported = rows.where(F.greatest("p_plus", "p_minus") >= MID).select("key", F.col("query_id").alias("hour"), F.lit(None).cast("bigint").alias("order_key"), F.col("query_id").alias("at"))
    orders = V.read_table(spark, sf_dir, "orders", ["o_orderkey", "o_custkey"]).join(vec.select(F.col("key").alias("o_custkey")).distinct(), "o_custkey", "left_semi")
    asked = orders.select(F.col("o_custkey").alias("key"), (F.col("o_orderkey") % 720).alias("hour"), F.col("o_orderkey").alias("order_key"), F.lit(None).cast("bigint").alias("at"))
    # One sort by key and time instead of a range join: reports come before orders of the same hour.
    past = Window.partitionBy("key").orderBy("hour", F.col("order_key").isNotNull()).rowsBetween(Window.unboundedPreceding, 0)
    both = reported.unionByName(asked).withColumn("reported_at", F.last("at", ignorenulls=True).over(past))
    return both.where("order_key is not null").select("order_key", "key", "hour", "reported_at")


@query(
    T.with_(
        *HOURLY, ("said", _INSIDE), ("moves", "SELECT query_id, key, inside, coalesce(lag(inside) OVER (PARTITION BY key ORDER BY query_id), false) AS was FROM said"),
        then="SELECT query_id, key, CASE WHEN inside THEN 'enters' ELSE 'leaves' END AS change FROM moves WHERE inside <> was",
    )
)
def report_changes(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = hourly_agreement(spark, sf_dir)[1].withColumn("inside", F.greatest("p_plus", "p_minus") >= MID)
    was = F.coalesce(F.lag("inside").over(Window.partitionBy("key").orderBy("query_id")), F.lit(False))
    moves = rows.withColumn("was", was).where("inside <> was")
    return moves.select("query_id", "key", F.when(F.col("inside"), "enters").otherwise("leaves").alias("change"))


_GAP = TAU_B - TAU_A
_P = "greatest(p_plus, p_minus)"


@query(
    T.with_(
        *HOURLY,
        ("said", f"SELECT query_id, key, CASE WHEN {_P} >= {TAU_B - _GAP / 5!r} THEN 1 WHEN {_P} < {TAU_A + _GAP / 5!r} THEN 0 END AS signal FROM agreed"),
        ("inside", "SELECT query_id, key FROM (SELECT *, last_value(signal IGNORE NULLS) OVER (PARTITION BY key ORDER BY query_id ROWS UNBOUNDED PRECEDING) AS state FROM said) WHERE state = 1"),
        ("ends", "SELECT *, lag(query_id) OVER w AS before, lead(query_id) OVER w AS after, (SELECT max(query_id) FROM inside) AS last FROM inside WINDOW w AS (PARTITION BY key ORDER BY query_id)"),
        ("moves", "SELECT key, CAST(count(*) FILTER (before IS NULL OR before < query_id - 1) + count(*) FILTER ((after IS NULL OR after > query_id + 1) AND query_id < last) AS BIGINT) AS changes FROM ends GROUP BY key"),
        ("levels", f"SELECT query_id, key, CASE WHEN {_P} <= {TAU_A + 2 * _GAP / 5!r} THEN 0 WHEN {_P} >= {TAU_B - 2 * _GAP / 5!r} THEN 1 END AS signal FROM agreed"),
        ("alt", "SELECT key, signal, coalesce(lag(signal) OVER (PARTITION BY key ORDER BY query_id), 0) AS before FROM levels WHERE signal IS NOT NULL"),
        ("turns", "SELECT key, CAST(count(*) FILTER (signal <> before) AS BIGINT) AS flips FROM alt GROUP BY key"),
        then="SELECT m.key, m.changes, t.flips, m.changes <= t.flips AS holds FROM moves m LEFT JOIN turns t ON m.key = t.key",
    )
)
def churn_against_flips(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Entries and exits of the continuous report beside the flips of the input: the report never changes oftener."""
    rows = hourly_agreement(spark, sf_dir)[1].persist()
    changes = M.churn(E.hysteresis_report(rows, TAU_A, TAU_B))
    joined = changes.join(M.flips(rows), "key", "left")
    return joined.select("key", "changes", "flips", (F.col("changes") <= F.col("flips")).alias("holds"))


# -- windows --------------------------------------------------------------------------------------
_EVENTS = "SELECT epoch(ts) AS t, user_id AS key, CAST(round(value * 100) AS BIGINT) AS value FROM events WHERE value IS NOT NULL"


def _updates(spark: SparkSession, sf_dir: str) -> DataFrame:
    events = V.read_table(spark, sf_dir, "events", ["ts", "user_id", "value"]).where("value is not null")
    return events.select("ts", F.col("user_id").alias("key"), V.cents("value").alias("value"))


def _windowed(spark: SparkSession, sf_dir: str, *window: str) -> DataFrame:
    cells = windowed_cells(_updates(spark, sf_dir), F.window("ts", *window), SMALL)
    return cells.select(F.unix_timestamp("w.start").alias("start"), "row", "bucket", "c")


@query(T.with_(("e", _EVENTS), ("sp", SMALL.sql("e")), then="SELECT CAST(floor(t / 3600) * 3600 AS BIGINT) AS start, row, bucket, CAST(sum(sign * value) AS BIGINT) AS c FROM sp GROUP BY ALL"))
def hourly_tumbling_cells(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _windowed(spark, sf_dir, "1 hour")


@query(T.with_(("e", _EVENTS), ("w", "SELECT key, value, CAST(floor(t / 3600) * 3600 - 3600 * b AS BIGINT) AS start FROM e, (SELECT unnest(range(0, 6)) AS b)"), ("sp", SMALL.sql("w")), then="SELECT start, row, bucket, CAST(sum(sign * value) AS BIGINT) AS c FROM sp GROUP BY ALL"))
def sliding_cells(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _windowed(spark, sf_dir, "6 hours", "1 hour")


@query(
    T.with_(
        ("e", _EVENTS), ("g", "SELECT *, CASE WHEN t - lag(t) OVER (PARTITION BY key ORDER BY t) < 10800 THEN 0 ELSE 1 END AS fresh FROM e"), ("s", "SELECT *, sum(fresh) OVER (PARTITION BY key ORDER BY t ROWS UNBOUNDED PRECEDING) AS session FROM g"),
        ("v", "SELECT key, CAST(sum(value) AS BIGINT) AS value, session FROM s GROUP BY ALL"), ("sp", SMALL.sql("v")),
        then="SELECT row, bucket, CAST(sum(sign * value) AS BIGINT) AS c, count(*) AS sessions FROM sp GROUP BY ALL",
    )
)
def session_cells(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Cells over the sums of sessions that end after three quiet hours."""
    sums = session_vectors(_updates(spark, sf_dir), "3 hours").select("key", "value")
    return SMALL.participation(sums).groupBy("row", "bucket").agg(F.sum(F.col("sign") * F.col("value")).alias("c"), F.count("*").alias("sessions"))


@query(T.with_(("vec", T.vector("user_values")), then=f"SELECT row, bucket, c AS stream, c AS batch, true AS equal FROM ({T.cells('vec', USERS)})"))
def stream_equals_batch(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The sketch a stream of files leaves behind, cell by cell beside that of one batch."""
    folder = scratch_path(spark, "stream")
    source = spark.read.parquet(f"{sf_dir}/events.parquet").select("user_id", "value")
    source.repartition(3).write.parquet(f"{folder}/in")
    running = RunningSketch(spark, f"{folder}/state", USERS)
    stream = spark.readStream.schema(source.schema).option("maxFilesPerTrigger", 1).parquet(f"{folder}/in")
    rows = stream.where("value is not null").select(F.col("user_id").alias("key"), V.cents("value").alias("value"))
    job = rows.writeStream.foreachBatch(running).option("checkpointLocation", f"{folder}/log").trigger(availableNow=True).start()
    job.awaitTermination()
    batch = S.build(V.user_values(spark, sf_dir), USERS, sum_keys=False).withColumnRenamed("c", "batch")
    both = running.cells().join(batch, S.CELL, "full_outer")
    return both.select("row", "bucket", F.col("c").alias("stream"), "batch", F.coalesce(F.col("c") == F.col("batch"), F.lit(False)).alias("equal"))


@query(
    T.with_(("vec", T.vector("url_hosts")), ("sp", USERS.sql("vec")), then="SELECT key, row, bucket, sign, value FROM sp")
)
def sql_functions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The registered SQL functions at work."""
    register(spark, USERS)
    V.url_hosts(spark, sf_dir).createOrReplaceTempView("steadysketch_hosts")
    return spark.sql(f"SELECT key, r AS row, row_bucket(key, r) AS bucket, row_sign(key, r) AS sign, value FROM (SELECT key, value, explode(sequence(0, {USERS.rows - 1})) AS r FROM steadysketch_hosts)")


@query(T.with_(("vec", T.vector("class_sums")), then=f"SELECT query_id, key, value FROM ({T.heavy('vec', 10)})"))
def sql_heavy_classes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The table function over all classes, one partition for each."""
    register(spark, USERS)
    V.class_sums(spark, sf_dir).createOrReplaceTempView("steadysketch_classes")
    return spark.sql("SELECT * FROM l2_heavy(TABLE(steadysketch_classes) PARTITION BY (query_id), 10)")
