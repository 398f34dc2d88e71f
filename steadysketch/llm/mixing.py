"""Mixing sources to target weights by Sainte-Lague apportionment of equal-token blocks.

Targets: the sources, in code-point order with null last, have weights 3, 1, 2, repeating, and share
``share`` times all words; a target stops at twice its source's size and the excess is shared again by
weight, which is water filling over the sources in order of size per weight.

Quotas: the total of blocks is apportioned to the sources by their targets, then each source's blocks
to its shards by their words, both by highest quotients votes / (2 k + 1). A party's seats differ from
its proportional share by less than 1.5 n times that share plus 2 among n parties, so only the
quotients in that range are ranked: a number of rows linear in the number of parties.

Selection: a shard lays its documents end to end in seeded order and cuts the line into blocks. A quota
of q blocks takes the whole line q div n times, and q mod n blocks from a seeded block on, cyclically;
as the order of the documents is random already, that run is a random sample of the line, and all but
its ends are whole documents. Nothing is taken more than twice.

Defined results: null text has size 0; rows with the same id count each; a null source is a source of
its own; a source without words has target 0. The block is 64 words, less where the smallest source has
under 64 blocks of that size. Only DataFrame functions are used; no source or shard meets in one task
with more than ``shard_docs`` documents on average.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..runtime import materialise
from .common import WORD

WEIGHTS = (3, 1, 2)
SHARE = 1.5
BLOCK = 64
SHARD_DOCS = 4_096
SEED = "mix-1"


def words(text: str = "text") -> Column:
    return F.coalesce(F.regexp_count(F.col(text), F.lit(WORD)), F.lit(0)).cast("long")


def targets(sources: DataFrame, share: float = SHARE, weights: Sequence[int] = WEIGHTS) -> DataFrame:
    """Adds weight and target to (source, source_size, docs); one row for each source."""
    by_name = Window.orderBy(F.col("source").asc_nulls_last())
    ranked = sources.withColumn("source_rank", F.row_number().over(by_name) - 1)
    weighted = ranked.withColumn("weight", F.element_at(F.array(*map(F.lit, weights)), (F.col("source_rank") % len(weights) + 1).cast("int")).cast("double"))
    everything = Window.partitionBy()
    before = Window.orderBy(2.0 * F.col("source_size") / F.col("weight"), "source_rank").rowsBetween(Window.unboundedPreceding, -1)
    full = F.col("source_size") * 2
    filled = weighted.withColumns(
        {
            "wanted": F.sum("source_size").over(everything) * share,
            "full_before": F.coalesce(F.sum(full).over(before), F.lit(0)),
            "weight_left": F.sum("weight").over(everything) - F.coalesce(F.sum("weight").over(before), F.lit(0.0)),
        }
    ).withColumn("level", (F.col("wanted") - F.col("full_before")) / F.col("weight_left"))
    filled = filled.withColumn("stops", full <= F.col("level") * F.col("weight"))
    level = F.max(F.when(~F.col("stops"), F.col("level"))).over(everything)
    target = F.when(F.col("stops"), full.cast("double")).otherwise(level * F.col("weight"))
    return filled.withColumn("target", target).select("source", "source_rank", "source_size", "docs", "weight", "target")


def apportion(parties: DataFrame, group: list[str], order: str, votes: str, seats: str, out: str) -> DataFrame:
    """Adds ``out``: the party's seats out of its group's ``seats`` by highest quotients, ties to the smaller ``order``."""
    whole = Window.partitionBy(*group)
    share = F.try_divide(F.col(votes), F.sum(votes).over(whole))
    sized = parties.withColumns({"_share": F.coalesce(share, F.lit(0.0)), "_n": F.count("*").over(whole)})
    quota = F.floor(F.col("_share") * F.col(seats))
    slack = (F.ceil(1.5 * F.col("_n") * F.col("_share")) + 2).cast("long")
    sized = sized.withColumns({"_sure": F.greatest(F.lit(0).cast("long"), quota - slack), "_most": quota + slack})
    sized = sized.withColumn("_left", F.col(seats) - F.sum("_sure").over(whole))
    offers = sized.where(f"{votes} > 0").select(*group, order, "_left", F.col(votes).alias("_v"), F.explode(F.sequence("_sure", "_most")).alias("_k"))
    ranked = offers.withColumn("_r", F.row_number().over(whole.orderBy((F.col("_v") / (2 * F.col("_k") + 1)).desc(), order, "_k")))
    won = ranked.where("_r <= _left").groupBy(*group, order).agg(F.count("*").alias("_won"))
    back = sized.join(won, [*group, order], "left")
    seats_won = F.when(F.col(votes) > 0, F.col("_sure") + F.coalesce("_won", F.lit(0))).otherwise(F.lit(0))
    return back.withColumn(out, seats_won.cast("long")).drop("_share", "_n", "_sure", "_most", "_left", "_won")


def _number(text: Column) -> Column:
    """A seeded number below 2^32 of a text, the same in any engine."""
    return F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("long")


def mix(docs: DataFrame, carry: Sequence[str] = (), share: float = SHARE, block: int = BLOCK, shard_docs: int = SHARD_DOCS, seed: str = SEED) -> DataFrame:
    """doc_id, size, source_size, target and taken (words the mix takes, repeats counted), and the carried columns."""
    kept = [F.col(c).alias(f"_carried_{c}") for c in carry]
    # Rows without an id are told apart by their text, so that they spread over the shards too.
    name = F.coalesce(F.col("doc_id").cast("string"), F.concat(F.lit("null/"), F.md5(F.coalesce("text", F.lit("")))))
    base = docs.select("doc_id", "source", words().alias("size"), name.alias("name"), *kept)
    if not carry:
        base = materialise(base, "sizes")
    sources = targets(base.groupBy("source").agg(F.sum("size").alias("source_size"), F.count("*").alias("docs")), share)
    everything = Window.partitionBy()
    smallest = F.min(F.when(F.col("source_size") > 0, F.col("source_size"))).over(everything)
    blocks = F.greatest(F.lit(1), F.least(F.lit(block), F.floor(F.coalesce(smallest, F.lit(0)) / 64))).cast("long")
    sources = sources.withColumn("block", blocks).withColumn("seats", F.round(F.sum("target").over(everything) / F.col("block")).cast("long"))
    sources = materialise(apportion(sources, [], "source_rank", "target", "seats", "source_seats"), "sources")

    facts = sources.select(F.col("source").alias("_source"), "source_rank", "source_size", "target", "block", "source_seats", F.ceil(F.col("docs") / shard_docs).cast("long").alias("shards"))
    mark = F.concat(F.lit(seed + "/"), F.col("name"))
    placed = base.join(facts, F.col("source").eqNullSafe(F.col("_source")))
    placed = placed.withColumn("place", F.md5(mark)).withColumn("shard", F.pmod(F.conv(F.substring("place", 25, 8), 16, 10).cast("long"), F.col("shards")))
    if carry:
        sizes = base.drop(*[f"_carried_{c}" for c in carry]).join(facts, F.col("source").eqNullSafe(F.col("_source")))
        sizes = sizes.withColumn("shard", F.pmod(F.conv(F.substring(F.md5(mark), 25, 8), 16, 10).cast("long"), F.col("shards")))
    else:
        sizes = placed
    shards = sizes.groupBy("source_rank", "shard", "source_seats", "block").agg(F.sum("size").alias("words"))
    shards = apportion(shards, ["source_rank"], "shard", "words", "source_seats", "quota")
    n = F.ceil(F.col("words") / F.col("block")).cast("long")
    shards = shards.withColumn("n", n).withColumn("quota", F.least("quota", 2 * F.col("n")))
    first = F.pmod(_number(F.concat_ws("/", F.lit(seed), F.col("source_rank"), F.col("shard"))), F.greatest("n", F.lit(1)))
    shards = shards.withColumns({"full": F.when(F.col("n") > 0, F.floor(F.col("quota") / F.col("n"))).otherwise(0).cast("long"), "first": first})
    shards = shards.withColumn("rest", F.col("quota") - F.col("full") * F.col("n")).select("source_rank", "shard", "n", "full", "first", "rest")

    line = Window.partitionBy("source_rank", "shard").orderBy("place", "doc_id", "size").rowsBetween(Window.unboundedPreceding, -1)
    laid = placed.withColumn("start", F.coalesce(F.sum("size").over(line), F.lit(0))).join(shards, ["source_rank", "shard"])

    def overlap(begin: Column, end: Column) -> Column:
        return F.greatest(F.lit(0), F.least(F.col("start") + F.col("size"), end) - F.greatest(F.col("start"), begin))

    begin, end = F.col("first") * F.col("block"), (F.col("first") + F.col("rest")) * F.col("block")
    around = (F.col("first") + F.col("rest") - F.col("n")) * F.col("block")
    taken = F.col("full") * F.col("size") + overlap(begin, end) + overlap(F.lit(0), around)
    return laid.select("doc_id", "size", "source_size", "target", taken.cast("long").alias("taken"), *[F.col(f"_carried_{c}").alias(f"mixed_{c}") for c in carry])


def mixed_documents(docs: DataFrame, **settings) -> DataFrame:
    """The mix as documents: each row as many times as the words taken from it, rounded, are its size; all columns stay."""
    columns = docs.columns
    found = mix(docs, columns, **settings)
    copies = F.when(F.col("size") > 0, F.round(F.col("taken") / F.col("size"))).otherwise(0).cast("int")
    return found.withColumn("copies", copies).where("copies > 0").withColumn("_copy", F.explode(F.sequence(F.lit(1), F.col("copies")))).select(*[F.col(f"mixed_{c}").alias(c) for c in columns])
