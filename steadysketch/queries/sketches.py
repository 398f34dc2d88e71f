"""Ground truth, hashing, sketch operations and the estimators without protection."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.hashing import sql_key
from ..operators import estimators as E
from ..operators import sketch as S
from ..operators.layouts import IndependentBuckets
from ..plans.physical import rollup_cells
from ..sources import vectors as V
from . import sqltext as T
from .base import BUCKETS, COMPACT, COMPONENTS, FLAT, LEVELS, MID, PARTS, SMALL, TOKENS, USERS, query


def keys(vec: DataFrame) -> DataFrame:
    return vec.select("query_id", "key")


def agreed(vec: DataFrame, layout, normalize: str = "expected") -> DataFrame:
    est = S.estimates(keys(vec), S.build(vec, layout, sum_keys=False), layout, 1)
    return E.agreement(E.votes(est), layout.per_key, normalize)


def agreed_sql(vector: str, layout, per_key: float | None) -> list[tuple[str, str]]:
    return [("vec", vector), ("cells", T.cells("vec", layout)), ("est", T.estimates("vec", "cells", layout)), ("votes", T.votes("est")), ("agreed", T.agreement("votes", per_key))]


# -- ground truth ---------------------------------------------------------------------------------
@query(T.with_(("vec", T.vector("doc_tokens")), then=T.heavy("vec", 10)))
def exact_heavy_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    return E.exact_heavy(V.doc_tokens(spark, sf_dir), 10, summed=True, queries=1)


@query(T.with_(("vec", T.vector("skewed_parts")), then=T.heavy("vec", 10)))
def exact_heavy_skewed_parts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return E.exact_heavy(V.skewed_parts(spark, sf_dir), 10, summed=True, queries=1)


@query(T.with_(("vec", T.vector("skewed_parts")), then=T.heavy("vec", 30, "full")))
def exact_heavy_full_norm(spark: SparkSession, sf_dir: str) -> DataFrame:
    return E.exact_heavy(V.skewed_parts(spark, sf_dir), 30, "full", summed=True, queries=1)


@query(T.with_(("vec", "SELECT query_id, key, value, value AS v_hat FROM (" + T.vector("doc_tokens") + ")"), then=f"SELECT query_id, key, value, rank FROM ({T.top('vec', 20)})"))
def exact_topk_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    return E.exact_topk(V.doc_tokens(spark, sf_dir), 20, summed=True)


@query(T.with_(("vec", T.vector("skewed_parts")), then=" UNION ALL ".join(f"SELECT {k} AS k, tail2 FROM ({T.tail2('vec', k)})" for k in (1, 4, 10, 30))))
def tail_norm_by_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    vec = V.skewed_parts(spark, sf_dir)
    out = None
    for k in (1, 4, 10, 30):
        part = E.tail_norm2(vec, k, summed=True, queries=1).select(F.lit(k).alias("k"), "tail2")
        out = part if out is None else out.unionAll(part)
    return out


@query(T.with_(("vec", T.vector("hourly_users")), then=T.heavy("vec", 4)))
def exact_heavy_per_hour(spark: SparkSession, sf_dir: str) -> DataFrame:
    return E.exact_heavy(V.hourly_users(spark, sf_dir), 4, summed=True)


# -- cells ----------------------------------------------------------------------------------------
@query(T.with_(("vec", T.vector("part_quantities")), then=T.cells("vec", FLAT)))
def row_hash_cells_parts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return S.build(V.part_quantities(spark, sf_dir), FLAT, sum_keys=False)


@query(T.with_(("vec", T.vector("skewed_parts")), then=T.cells("vec", BUCKETS)))
def independent_cells_parts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return S.build(V.skewed_parts(spark, sf_dir), BUCKETS, sum_keys=False)


@query()
def skip_cells_parts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return S.build(V.skewed_parts(spark, sf_dir), IndependentBuckets(BUCKETS.buckets, BUCKETS.width, BUCKETS.seed, "skip"))


@query(T.with_(("vec", T.vector("skewed_parts")), then=f"SELECT key, count(*) AS part FROM ({BUCKETS.sql('vec')}) GROUP BY ALL"))
def participation_sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return BUCKETS.participation(keys(V.skewed_parts(spark, sf_dir))).groupBy("key").agg(F.count("*").alias("part"))


@query(T.with_(("vec", T.vector("user_values")), then=T.cells("vec", USERS)))
def merged_daily_cells(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A sketch for each day, merged: equals the sketch of all days."""
    events = V.read_table(spark, sf_dir, "events", ["ts", "user_id", "value"])
    rows = events.select(F.to_date("ts").alias("day"), F.col("user_id").alias("key"), V.cents("value").alias("value")).where("value is not null")
    daily = S.build_by(rows, ["day"], USERS)
    return S.merge(daily.select(F.lit(0).cast("bigint").alias("query_id"), "row", "bucket", "c"))


@query(T.with_(("vec", T.vector("part_quantities")), then=T.cells("vec", FLAT)))
def incremental_cells(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Half of the rows sketched, the other half applied as an update."""
    rows = V.read_table(spark, sf_dir, "lineitem", ["l_orderkey", "l_partkey", "l_quantity"])
    half = lambda cond: V.vector_from(rows.where(cond), F.col("l_partkey"), F.col("l_quantity").cast("bigint"))
    return S.update(S.build(half("l_orderkey % 2 = 0"), FLAT, sum_keys=False), half("l_orderkey % 2 <> 0"), FLAT)


@query(
    T.with_(
        ("a", T.vector("user_values")), ("b", T.vector("net_users")), ("vec", "SELECT query_id, key, 3 * value AS value FROM a UNION ALL SELECT query_id, key, -value FROM b"), then=T.cells("vec", USERS)
    )
)
def scaled_difference_cells(spark: SparkSession, sf_dir: str) -> DataFrame:
    a, b = S.build(V.user_values(spark, sf_dir), USERS, sum_keys=False), S.build(V.net_users(spark, sf_dir), USERS, sum_keys=False)
    return S.merge(S.scale(a, 3), S.scale(b, -1))


_GROUPED = f"SELECT lang, source, {sql_key('token')} AS key, count(*) AS value FROM (SELECT lang, source, unnest(string_split(replace(lower(text), chr(10), ' '), ' ')) AS token FROM documents) WHERE token <> '' GROUP BY ALL"


@query(
    T.with_(
        ("vec", _GROUPED),
        ("spread", SMALL.sql("vec")),
        then="SELECT lang, source, row, bucket, CAST(sum(sign * value) AS BIGINT) AS c, CAST(grouping(lang, source) AS INTEGER) AS level FROM spread GROUP BY GROUPING SETS ((lang, source, row, bucket), (lang, row, bucket), (row, bucket))",
    )
)
def cube_cells_language_source(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A sketch for each language and source, and all totals, rolled up from cells alone."""
    docs = V.read_table(spark, sf_dir, "documents", ["lang", "source", "text"])
    rows = V.tokens_of(docs).select("lang", "source", V.key_from_string(F.col("token")).alias("key"), F.lit(1).cast("bigint").alias("value"))
    cells = S.build_by(rows, ["lang", "source"], SMALL)
    levels = cells.groupingSets([["lang", "source", "row", "bucket"], ["lang", "row", "bucket"], ["row", "bucket"]], "lang", "source", "row", "bucket")
    return levels.agg(F.sum("c").alias("c"), (F.grouping("lang") * 2 + F.grouping("source")).cast("int").alias("level"))


@query(
    T.with_(
        ("vec", "SELECT *, 'x' AS lang FROM (" + T.vector("user_values") + ")"),
        ("spread", USERS.sql("vec")),
        then="SELECT row, bucket, CAST(sum(sign * value) AS BIGINT) AS c, CAST(count(DISTINCT lang) AS BIGINT) AS groups FROM spread GROUP BY ALL",
    )
)
def rolled_up_cells(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Totals over days by rolling cells up: the coarsest level."""
    events = V.read_table(spark, sf_dir, "events", ["ts", "user_id", "value"])
    rows = events.select(F.to_date("ts").alias("day"), F.col("user_id").alias("key"), V.cents("value").alias("value")).where("value is not null")
    total = rollup_cells(S.build_by(rows, ["day"], USERS).select("row", "bucket", "day", "c"), [])
    return total.select("row", "bucket", "c", F.lit(1).cast("bigint").alias("groups"))


@query(
    T.with_(
        ("a", T.vector("user_values")), ("b", T.vector("net_users")), ("ca", T.cells("a", USERS)), ("cb", T.cells("b", USERS)),
        ("by_row", "SELECT ca.query_id, ca.row, sum(ca.c * cb.c) AS p FROM ca JOIN cb ON ca.query_id = cb.query_id AND ca.row = cb.row AND ca.bucket = cb.bucket GROUP BY ALL"),
        then="SELECT query_id, CAST(median(CAST(p AS BIGINT)) AS DOUBLE) AS product FROM by_row GROUP BY ALL",
    )
)
def sketch_inner_product(spark: SparkSession, sf_dir: str) -> DataFrame:
    return S.inner_product(S.build(V.user_values(spark, sf_dir), USERS, sum_keys=False), S.build(V.net_users(spark, sf_dir), USERS, sum_keys=False))


@query(
    T.with_(("vec", T.vector("skewed_parts")), ("cells", T.cells("vec", USERS)), ("by_row", "SELECT query_id, row, sum(c * c) AS p FROM cells GROUP BY ALL"), then="SELECT query_id, CAST(median(CAST(p AS BIGINT)) AS DOUBLE) AS norm2 FROM by_row GROUP BY ALL")
)
def sketch_norm2(spark: SparkSession, sf_dir: str) -> DataFrame:
    return S.norm2(S.build(V.skewed_parts(spark, sf_dir), USERS, sum_keys=False))


@query(T.with_(("vec", T.vector("url_hosts")), ("cells", T.cells("vec", FLAT)), then=T.estimates("vec", "cells", FLAT)))
def bucket_estimates_sample(spark: SparkSession, sf_dir: str) -> DataFrame:
    vec = V.url_hosts(spark, sf_dir)
    return S.estimates(keys(vec), S.build(vec, FLAT, sum_keys=False), FLAT, 1)


@query(
    T.with_(
        ("vec", T.vector("class_sums")), ("cells", T.cells("vec", SMALL)), ("spots", f"SELECT DISTINCT c.query_id, s AS spot FROM cells c, (SELECT unnest(range(0, {SMALL.size})) AS s)"),
        then=f"SELECT s.query_id, CAST(s.spot AS INTEGER) AS spot, CAST(coalesce(c.c, 0) AS DOUBLE) AS feature FROM spots s LEFT JOIN cells c ON c.query_id = s.query_id AND c.row * {SMALL.width} + c.bucket = s.spot",
    )
)
def embedded_classes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sketches as dense features, one row for each feature."""
    dense = S.embed(S.build(V.class_sums(spark, sf_dir), SMALL, sum_keys=False), SMALL)
    return dense.select("query_id", F.posexplode("features").alias("spot", "feature"))


# -- medians --------------------------------------------------------------------------------------
def _median_sql(vector: str, layout) -> list[tuple[str, str]]:
    return [("vec", T.vector(vector)), ("cells", T.cells("vec", layout)), ("est", T.estimates("vec", "cells", layout)), ("med", T.medians("est"))]


def estimated(vec: DataFrame, layout) -> DataFrame:
    return S.estimates(keys(vec), S.build(vec, layout, sum_keys=False), layout, 1)


@query(T.with_(*_median_sql("user_values", USERS), then="SELECT * FROM med"))
def median_estimates_users(spark: SparkSession, sf_dir: str) -> DataFrame:
    return E.median_estimate(estimated(V.user_values(spark, sf_dir), USERS))


@query(T.with_(*_median_sql("doc_tokens", TOKENS), then=T.top("med", 20)))
def median_report_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    return E.median_report(estimated(V.doc_tokens(spark, sf_dir), TOKENS), E.report_size(10, 0.0))


@query(T.with_(*_median_sql("skewed_parts", PARTS)[:3], then="SELECT query_id, key, round(quantile_cont(CAST(est AS DOUBLE), 0.45), 6) AS v_hat FROM est GROUP BY ALL"))
def quantile_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    return E.quantile_estimate(estimated(V.skewed_parts(spark, sf_dir), PARTS), 0.45).withColumn("v_hat", F.round("v_hat", 6))


@query(T.with_(*_median_sql("skewed_parts", BUCKETS), then="SELECT * FROM med"))
def median_independent(spark: SparkSession, sf_dir: str) -> DataFrame:
    return E.median_estimate(estimated(V.skewed_parts(spark, sf_dir), BUCKETS))


@query(T.with_(*_median_sql("embedding_rows", COMPONENTS), then="SELECT * FROM med"))
def reconstruct_embedding(spark: SparkSession, sf_dir: str) -> DataFrame:
    vec = V.embedding_rows(spark, sf_dir)
    return E.median_estimate(S.own_estimates(vec, COMPONENTS))


# -- sign agreement -------------------------------------------------------------------------------
@query(T.with_(*agreed_sql(T.vector("conversation_tokens"), TOKENS, None)[:4], then="SELECT * FROM votes"))
def sign_votes_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    return E.votes(estimated(V.conversation_tokens(spark, sf_dir), TOKENS))


@query(T.with_(*agreed_sql(T.vector("skewed_parts"), PARTS, 129), then="SELECT query_id, key, round(p_plus, 6) AS p_plus, round(p_minus, 6) AS p_minus FROM agreed"))
def basic_agreement(spark: SparkSession, sf_dir: str) -> DataFrame:
    return agreed(V.skewed_parts(spark, sf_dir), PARTS).select("query_id", "key", F.round("p_plus", 6).alias("p_plus"), F.round("p_minus", 6).alias("p_minus"))


def _reported(report: DataFrame) -> DataFrame:
    return report.withColumn("p_hat", F.round("p_hat", 6))


_REPORTED = "SELECT query_id, key, sign, round(p_hat, 6) AS p_hat FROM ({})"


@query(T.with_(*agreed_sql(T.vector("doc_tokens"), TOKENS, 65), then=_REPORTED.format(T.threshold("agreed", MID))))
def threshold_report_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _reported(E.threshold_report(agreed(V.doc_tokens(spark, sf_dir), TOKENS), MID))


@query(T.with_(*agreed_sql(T.vector("source_contrast"), TOKENS, 65), then=_REPORTED.format(T.threshold("agreed", MID))))
def threshold_report_contrast(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _reported(E.threshold_report(agreed(V.source_contrast(spark, sf_dir), TOKENS), MID))


@query(T.with_(*agreed_sql(T.vector("skewed_parts"), BUCKETS, None), then=_REPORTED.format(T.threshold("agreed", COMPACT))))
def threshold_report_independent(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _reported(E.threshold_report(agreed(V.skewed_parts(spark, sf_dir), BUCKETS, "realized"), COMPACT))


_SWEEP = (0.6, 0.7, 0.8, 0.85, 0.9, 0.95, 0.99)


@query(T.with_(*agreed_sql(T.vector("skewed_parts"), PARTS, 129), then=f"SELECT CAST(t AS DOUBLE) AS tau, count(*) FILTER (greatest(p_plus, p_minus) >= t) AS reported FROM agreed, (SELECT unnest({list(_SWEEP)}::DOUBLE[]) AS t) GROUP BY ALL"))
def threshold_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    taus = F.explode(F.array(*map(F.lit, _SWEEP))).alias("tau")
    rows = agreed(V.skewed_parts(spark, sf_dir), PARTS).select(F.greatest("p_plus", "p_minus").alias("p"), taus)
    return rows.groupBy("tau").agg(F.count(F.when(F.col("p") >= F.col("tau"), 1)).alias("reported"))


@query(
    T.with_(
        *agreed_sql(T.vector("part_quantities"), PARTS, 129), ("med", T.medians("est")),
        then=f"SELECT (SELECT count(*) FROM ({T.top('med', 10)})) AS forced, (SELECT count(*) FROM ({T.threshold('agreed', MID)})) AS reported, (SELECT count(*) FROM ({T.heavy('vec', 10)})) AS heavy",
    )
)
def no_heavy_empty_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A flat vector: a forced top-k names keys, the threshold rule names none."""
    vec = V.part_quantities(spark, sf_dir)
    est = estimated(vec, PARTS)
    counts = [
        E.median_report(est, 10).agg(F.count("*").alias("forced")),
        E.threshold_report(E.agreement(E.votes(est), PARTS.per_key), MID).agg(F.count("*").alias("reported")),
        E.exact_heavy(vec, 10, summed=True, queries=1).agg(F.count("*").alias("heavy")),
    ]
    return counts[0].crossJoin(counts[1]).crossJoin(counts[2])


def hourly_agreement(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """The hourly vectors, and the agreement of every user in the hours that have the user.

    The candidates of an hour are its own keys. The hour after one that had a user follows with agreement
    0 where it has not, so that a user who is gone leaves every report; no pair of hour and user is made
    besides.
    """
    vec = V.hourly_users(spark, sf_dir)
    est = S.estimates(keys(vec), S.build(vec, USERS, sum_keys=False), USERS)
    said = E.agreement(E.votes(est), USERS.per_key)
    end = vec.agg(F.max("query_id").alias("end"))
    after = F.lead("query_id").over(Window.partitionBy("key").orderBy("query_id"))
    gone = keys(vec).withColumn("after", after).crossJoin(F.broadcast(end)).where("after > query_id + 1 or (after is null and query_id < end)")
    zero = {c: F.lit(0).cast(t) for c, t in said.dtypes if c not in ("query_id", "key")}
    return vec, said.unionByName(gone.select((F.col("query_id") + 1).alias("query_id"), "key", *[v.alias(c) for c, v in zero.items()]))


HOURLY = [
    ("vec", T.vector("hourly_users")), ("cells", T.cells("vec", USERS)), ("est", T.estimates("vec", "cells", USERS)), ("votes", T.votes("est")), ("present", T.agreement("votes", 33)),
    ("steps", "SELECT query_id, key, lead(query_id) OVER (PARTITION BY key ORDER BY query_id) AS after, (SELECT max(query_id) FROM vec) AS last FROM vec"),
    ("agreed", "SELECT query_id, key, pos, neg, p_plus, p_minus FROM present UNION ALL SELECT query_id + 1, key, 0, 0, 0, 0 FROM steps WHERE after > query_id + 1 OR (after IS NULL AND query_id < last)"),
]
_IN, _OUT = LEVELS[1] - (LEVELS[1] - LEVELS[0]) / 5, LEVELS[0] + (LEVELS[1] - LEVELS[0]) / 5


@query(
    T.with_(
        *HOURLY,
        ("said", f"SELECT query_id, key, greatest(p_plus, p_minus) AS p, CASE WHEN greatest(p_plus, p_minus) >= {_IN!r} THEN 1 WHEN greatest(p_plus, p_minus) < {_OUT!r} THEN 0 END AS signal FROM agreed"),
        ("states", "SELECT *, last_value(signal IGNORE NULLS) OVER (PARTITION BY key ORDER BY query_id ROWS UNBOUNDED PRECEDING) AS inside FROM said"),
        then="SELECT query_id, key, round(p, 6) AS p_hat FROM states WHERE inside = 1",
    )
)
def hysteresis_hours(spark: SparkSession, sf_dir: str) -> DataFrame:
    return E.hysteresis_report(hourly_agreement(spark, sf_dir)[1], *LEVELS).withColumn("p_hat", F.round("p_hat", 6))


@query()
def agreement_truth_tags(spark: SparkSession, sf_dir: str) -> DataFrame:
    vec = V.html_tags(spark, sf_dir)
    spread = int(vec.agg(F.sum(F.abs("value"))).first()[0] or 1)
    return E.true_agreement(vec, keys(vec), SMALL.width, spread)


@query(T.with_(*agreed_sql(T.vector("embedding_rows"), COMPONENTS, 21), then=_REPORTED.format(T.threshold("agreed", COMPACT))))
def batch_report_embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    vec = V.embedding_rows(spark, sf_dir)
    est = S.own_estimates(vec, COMPONENTS)
    return _reported(E.threshold_report(E.agreement(E.votes(est), COMPONENTS.per_key), COMPACT))
