"""Joins, set operations, formats, functions and streams around the methods."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..functions.hashing import PRIME, coefficients, poly_hash, rowcoef, sql_key, sql_poly
from ..operators import estimators as E
from ..operators import sketch as S
from ..plans.physical import sized_broadcast
from ..runtime import materialise, scratch_path
from ..sources import io
from ..sources import vectors as V
from ..streaming.continuous import stream_updates, windowed_cells
from . import sqltext as T
from .base import MID, PARTS, SMALL, TOKENS, USERS, query
from .sketches import HOURLY, agreed, agreed_sql, estimated, hourly_agreement, keys


# -- joins ----------------------------------------------------------------------------------------
_HINTED = T.with_(*agreed_sql(T.vector("skewed_parts"), PARTS, 129), ("report", T.threshold("agreed", MID)), then="SELECT h AS hint, r.key, count(l.l_orderkey) AS lines FROM report r JOIN lineitem l ON r.key = l.l_partkey, (SELECT unnest(['merge', 'shuffle_hash']) AS h) GROUP BY ALL")


@query(_HINTED)
def hinted_joins(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Lines of the reported parts, with the join asked to sort and merge and asked to build shuffled hash tables."""
    report = materialise(E.threshold_report(agreed(V.skewed_parts(spark, sf_dir), PARTS), MID).select("key"), "report")
    lines = V.read_table(spark, sf_dir, "lineitem", ["l_partkey", "l_orderkey"])
    out = None
    for hint in ("merge", "shuffle_hash"):
        part = lines.join(report.hint(hint), F.col("l_partkey") == F.col("key")).groupBy("key").agg(F.count("l_orderkey").alias("lines")).select(F.lit(hint).alias("hint"), "key", "lines")
        out = part if out is None else out.unionAll(part)
    return out


@query(T.with_(*HOURLY, ("r", f"SELECT query_id, key FROM agreed WHERE greatest(p_plus, p_minus) >= {MID!r}"), then="SELECT r.key, r.query_id, v.query_id AS hour, v.value FROM r JOIN vec v ON v.key = r.key AND v.query_id BETWEEN r.query_id - 2 AND r.query_id + 2"))
def report_neighbourhood(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A band join: what a reported user did in the two hours before and after. Bins as wide as the band make it an equi-join."""
    vec, rows = hourly_agreement(spark, sf_dir)
    reported = rows.where(F.greatest("p_plus", "p_minus") >= MID).select("key", "query_id")
    band = F.floor(F.col("query_id") / 5)
    bins = F.array_distinct(F.array(F.floor((F.col("query_id") - 2) / 5), F.floor((F.col("query_id") + 2) / 5)))
    left = reported.select("key", "query_id", F.explode(bins).alias("bin"))
    right = vec.select(F.col("key").alias("k"), F.col("query_id").alias("hour"), "value", band.alias("b"))
    near = F.col("hour").between(F.col("query_id") - 2, F.col("query_id") + 2)
    return left.join(right, (F.col("key") == F.col("k")) & (F.col("bin") == F.col("b")) & near).select("key", "query_id", "hour", "value")


# -- shapes ---------------------------------------------------------------------------------------
_LANGS = ("de", "en", "es", "fr")


@query(
    T.with_(
        ("vec", f"SELECT lang, {sql_key('token')} AS key, count(*) AS value FROM (SELECT lang, unnest(string_split(replace(lower(text), chr(10), ' '), ' ')) AS token FROM documents) WHERE token <> '' GROUP BY ALL"), ("sp", SMALL.sql("vec")),
        then="SELECT row, bucket, " + ", ".join(f"CAST(sum(sign * value) FILTER (lang = '{x}') AS BIGINT) AS {x}" for x in _LANGS) + " FROM sp GROUP BY ALL",
    )
)
def pivoted_cells(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sketches of the languages side by side, a column for each."""
    docs = V.read_table(spark, sf_dir, "documents", ["lang", "text"])
    rows = V.tokens_of(docs).select("lang", V.key_from_string(F.col("token")).alias("key"), F.lit(1).cast("bigint").alias("value"))
    return S.build_by(rows, ["lang"], SMALL).groupBy("row", "bucket").pivot("lang", list(_LANGS)).agg(F.sum("c"))


_SETS = T.with_(
    ("a", f"SELECT key FROM ({T.vector('doc_tokens')}) ORDER BY abs(value) DESC, key LIMIT 40"), ("b", f"SELECT key FROM ({T.vector('conversation_tokens')}) ORDER BY abs(value) DESC, key LIMIT 40"),
    then="SELECT 'both' AS part, key FROM (SELECT key FROM a INTERSECT SELECT key FROM b) UNION ALL SELECT 'first alone', key FROM (SELECT key FROM a EXCEPT SELECT key FROM b) UNION ALL SELECT 'second alone', key FROM (SELECT key FROM b EXCEPT SELECT key FROM a) UNION ALL SELECT 'either', key FROM (SELECT key FROM a UNION SELECT key FROM b)",
)


@query(_SETS)
def report_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The top tokens of documents and conversations: common, alone and together."""
    a, b = (materialise(E.exact_topk(v(spark, sf_dir), 40, summed=True).select("key"), "top") for v in (V.doc_tokens, V.conversation_tokens))
    parts = {"both": a.intersect(b), "first alone": a.exceptAll(b), "second alone": b.exceptAll(a), "either": a.union(b).distinct()}
    out = None
    for name, part in parts.items():
        named = part.select(F.lit(name).alias("part"), "key")
        out = named if out is None else out.unionAll(named)
    return out


_SHARE = PRIME // 4


@query(T.with_(("e", f"SELECT user_id AS key, CAST(round(value * 100) AS BIGINT) AS value FROM events WHERE value IS NOT NULL AND {sql_poly('event_id', coefficients(55, 0, 1, 3), '0')} < {_SHARE}"), ("v", "SELECT 0 AS query_id, key, CAST(sum(value) AS BIGINT) * 4 AS value FROM e GROUP BY ALL"), then=T.cells("v", USERS)))
def sampled_cells(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The sketch of a quarter of the events, drawn by a hash of their ids and scaled up: an unbiased estimate of the whole."""
    events = V.read_table(spark, sf_dir, "events", ["event_id", "user_id", "value"]).where(F.col("value").isNotNull())
    drawn = events.where(poly_hash(F.col("event_id"), [F.lit(c[0]).cast("bigint") for c in coefficients(55, 0, 1, 3)]) < _SHARE)
    vec = V.vector_from(drawn, F.col("user_id"), V.cents("value"))
    return S.scale(S.build(vec, USERS, sum_keys=False), 4)


@query("SELECT user_id AS query_id, CAST(json_extract(props, '$.k') AS BIGINT) AS key, count(*) AS value FROM events WHERE json_extract(props, '$.k') IS NOT NULL GROUP BY ALL")
def json_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A vector for each user: counts by an integer field of the events' JSON text."""
    return io.from_json(V.read_table(spark, sf_dir, "events", ["user_id", "props"]), "user_id", "props", "$.k")


@query(T.with_(("vec", T.vector("url_hosts")), ("c", T.cells("vec", SMALL)), then="SELECT k AS kind, count(*) AS cells, CAST(sum(c.c * (c.row + 1)) AS BIGINT) AS weighted FROM c, (SELECT unnest(['parquet', 'orc', 'json', 'csv']) AS k) GROUP BY ALL"))
def formats_round_trip(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Cells written to and read back from files of every kind, and from a folder partitioned by sketch."""
    cells = S.build(V.url_hosts(spark, sf_dir), SMALL, sum_keys=False)
    folder = scratch_path(spark, "formats")
    io.write_cells(cells, f"{folder}/cells", "hosts", "overwrite")
    cells = io.read_cells(spark, f"{folder}/cells", "hosts")
    schema = "query_id bigint, row int, bucket int, c bigint"
    out = None
    for kind in ("parquet", "orc", "json", "csv"):
        cells.select("query_id", "row", "bucket", "c").write.format(kind).save(f"{folder}/{kind}")
        back = io.read_rows(spark, f"{folder}/{kind}", kind, schema if kind in ("json", "csv") else None, ["row", "c"])
        part = back.agg(F.count("*").alias("cells"), F.sum(F.col("c") * (F.col("row") + 1)).alias("weighted")).select(F.lit(kind).alias("kind"), "cells", "weighted")
        out = part if out is None else out.unionAll(part)
    return out


_ROWCOEF = ", ".join(f"({row}, '{name}', [{', '.join(f'{c[row]}::BIGINT' for c in coefficients(SMALL.seed, k, SMALL.rows, SMALL.degree))}])" for k, name in enumerate(("bucket", "sign")) for row in range(SMALL.rows))


_COEF = f"SELECT row, role, i - 1 AS power, a[i] AS coefficient FROM (VALUES {_ROWCOEF}) AS t(row, role, a), (SELECT unnest(range(1, {SMALL.degree + 2})) AS i)"
_POWERS = f"SELECT n, CASE i WHEN 0 THEN 1 WHEN 1 THEN k % {PRIME} ELSE (k * k) % {PRIME} END AS p, i AS power FROM (SELECT CAST(l_partkey AS BIGINT) AS k, count(*) AS n FROM lineitem WHERE l_partkey IS NOT NULL GROUP BY ALL), (SELECT unnest(range(0, {SMALL.degree + 1})) AS i)"


@query(f"SELECT c.row, c.role, c.power, c.coefficient, CAST(sum(p.n) AS BIGINT) AS keyed, CAST(sum((c.coefficient * p.p) % {PRIME} * p.n) AS BIGINT) AS terms FROM ({_COEF}) c JOIN ({_POWERS}) p ON c.power = p.power GROUP BY ALL")
def row_coefficients(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The hash coefficients of a layout as a table, each with the sum of its terms over the part keys of all line items."""
    coefs = rowcoef(spark, SMALL.seed, SMALL.rows, ["bucket", "sign"], SMALL.degree).select("row", "role", F.posexplode("a").alias("power", "coefficient"))
    keyed = V.read_table(spark, sf_dir, "lineitem", ["l_partkey"]).where("l_partkey is not null").groupBy(F.col("l_partkey").cast("bigint").alias("k")).agg(F.count("*").alias("n"))
    # A key's powers are those of the layout's degree, 2.
    powers = keyed.select("n", F.posexplode(F.array(F.lit(1).cast("bigint"), F.col("k") % PRIME, F.col("k") * F.col("k") % PRIME)).alias("power", "p"))
    both = powers.join(sized_broadcast(coefs, SMALL.rows * 2 * (SMALL.degree + 1)), "power")
    return both.groupBy("row", "role", "power", "coefficient").agg(F.sum("n").alias("keyed"), F.sum(F.col("coefficient") * F.col("p") % PRIME * F.col("n")).alias("terms"))


# -- functions ------------------------------------------------------------------------------------
@query(T.with_(("vec", T.vector("html_tags")), ("cells", T.cells("vec", TOKENS)), ("est", T.estimates("vec", "cells", TOKENS)), then="SELECT * FROM (" + T.medians("est") + ")"))
def arrow_medians(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Medians of the bucket estimates by a function over Arrow arrays, a key's estimates in one value."""
    import pyarrow.compute as pc

    @F.arrow_udf("double")
    def middle(estimates: pa.Array) -> pa.Array:
        return pa.array([pc.quantile(row.values, 0.5)[0].as_py() for row in estimates], pa.float64())

    held = estimated(V.html_tags(spark, sf_dir), TOKENS).groupBy("query_id", "key").agg(F.collect_list("est").alias("e"))
    return held.select("query_id", "key", middle("e").alias("v_hat"))


@query(T.with_(("vec", T.vector("class_sums")), ("cells", T.cells("vec", SMALL)), ("by_row", "SELECT query_id, row, sum(c * c) AS p FROM cells GROUP BY ALL"), then="SELECT query_id, CAST(median(CAST(p AS BIGINT)) AS DOUBLE) AS norm2 FROM by_row GROUP BY ALL"))
def norm2_udaf(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The norm estimate as an aggregate function over cells, one call for each group."""

    @F.pandas_udf("double")
    def sketch_norm2(row: pd.Series, c: pd.Series) -> float:
        return float((c.astype("float64") ** 2).groupby(row).sum().median())

    cells = S.build(V.class_sums(spark, sf_dir), SMALL, sum_keys=False)
    return cells.groupBy("query_id").agg(sketch_norm2("row", "c").alias("norm2"))


# -- streams --------------------------------------------------------------------------------------
def _totals(key: tuple[int], batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
    total = state.get[0] if state.exists else 0
    total += int(sum(rows.value.sum() for rows in batches))
    state.update((total,))
    yield pd.DataFrame({"key": [key[0]], "total": [total]})


@query()
def stream_modes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same events as a stream in all output modes, beside the batch: windows with a watermark appended, cells complete, totals of a stateful operator updated."""
    folder = scratch_path(spark, "modes")
    source = spark.read.parquet(f"{sf_dir}/events.parquet").select("ts", "user_id", "value")
    source.orderBy("ts").coalesce(1).write.option("maxRecordsPerFile", max(1, -(-source.count() // 2))).parquet(f"{folder}/in")
    updates = lambda: stream_updates(spark, f"{folder}/in", source.schema, F.col("user_id"), V.cents("value"), files_per_trigger=2)

    def run(frame: DataFrame, mode: str) -> DataFrame:
        name = f"steadysketch_{mode}"
        job = frame.writeStream.outputMode(mode).format("memory").queryName(name).option("checkpointLocation", f"{folder}/{mode}").trigger(availableNow=True).start()
        job.awaitTermination()
        return spark.table(name)

    windows = windowed_cells(updates(), F.window("ts", "1 hour"), SMALL, late="1 hour")
    appended = run(windows.select(F.unix_timestamp("w.start").alias("start"), "row", "bucket", "c"), "append")
    spread = SMALL.participation(updates().select("key", "value"))
    complete = run(spread.groupBy("row", "bucket").agg(F.sum(F.col("sign") * F.col("value")).alias("c")), "complete")
    totals = updates().groupBy("key").applyInPandasWithState(_totals, "key bigint, total bigint", "total bigint", "update", GroupStateTimeout.NoTimeout)
    updated = run(totals, "update").groupBy("key").agg(F.count("*").alias("updates"), F.max("total").alias("total"))
    vec = V.user_values(spark, sf_dir)
    batch = S.build(vec, SMALL, sum_keys=False)
    hours = windowed_cells(V.read_table(spark, sf_dir, "events", ["ts", "user_id", "value"]).where("value is not null").select("ts", F.col("user_id").alias("key"), V.cents("value").alias("value")), F.window("ts", "1 hour"), SMALL)
    hours = hours.select(F.unix_timestamp("w.start").alias("start"), "row", "bucket", "c")
    same = lambda a, b, on: a.join(b, on).count()
    rows = [
        ("append", appended.count(), same(appended, hours, ["start", "row", "bucket", "c"])),
        ("complete", complete.count(), same(complete, batch, ["row", "bucket", "c"])),
        ("update", updated.count(), same(updated.select("key", F.col("total").alias("value")), vec, ["key", "value"])),
    ]
    return spark.createDataFrame(rows, "mode string, rows bigint, as_in_batch bigint")
