"""Quality by perplexity under a Kneser-Ney model of trusted text, and selection by cross-entropy difference.

Trusted text is that of documents labelled with quality 1. Four fifths of it, by a hash of the id, train
the model; the rest tells what perplexity clean text of a language has when the model has not seen it. A
document is kept if its perplexity is at most ``margin`` times its language's ``quantile`` there. The
quantile is one that fifty documents can estimate and that a few odd ones among them do not move. A
language with fewer than MIN_CALIBRATION such documents (a null language is one of its own) has the
quantile of all of them. Quantiles are taken over perplexities in steps of a thousandth of their logarithm,
so they are exact, mergeable counts and the same in every run.

The cross-entropy difference scores a document by its mean loss per token under a target model (trusted
text) less that under a background model, negative meaning closer to the target. The background is a share
of all documents, taken by a hash, that has as much text as the target; both models have the same order
and the same vocabulary.

Defined results: a null or empty text has no tokens, a null perplexity and score, and is not kept; with
nothing to train on every model is uniform and all texts are kept; labels of ids without document, null
ids and repeated labels change nothing; repeated rows are scored each.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..runtime import materialise
from .ngram_lm import ORDER, Model, counts, estimate, losses

#: Order of the two models whose losses are compared.
SELECTION_ORDER = 6
QUANTILE, MARGIN = 0.9, 1.15
MIN_CALIBRATION = 50
STEPS = 1000
#: Most labelled ids that are broadcast; more are joined by a shuffle.
BROADCAST_IDS = 2_000_000
BROADCAST_LANGUAGES = 10_000


def trusted_ids(labels: DataFrame) -> DataFrame:
    found = materialise(labels.where("quality = 1 and doc_id is not null").select("doc_id").distinct(), "trusted")
    return F.broadcast(found) if found.count() <= BROADCAST_IDS else found


def _fifth(doc_id: str = "doc_id") -> Column:
    return F.pmod(F.xxhash64(F.col(doc_id), F.lit("calibration")), F.lit(5))


def _perplexity() -> Column:
    return F.when(F.col("n_tokens") > 0, F.exp(F.col("loss_trusted") / F.col("n_tokens")))


def thresholds(scored: DataFrame, quantile: float = QUANTILE, margin: float = MARGIN) -> tuple[DataFrame, float | None]:
    """(lang, threshold) of languages with enough scored calibration documents, and the threshold of all together."""
    step = F.ceil(F.log("perplexity") * STEPS).cast("long")
    bins = materialise(scored.where("perplexity is not null").groupBy("lang", step.alias("step")).agg(F.count("*").alias("n")), "bins")

    def first_over(frame: DataFrame, by: list[str]) -> DataFrame:
        whole = Window.partitionBy(*by)
        upto = F.sum("n").over(whole.orderBy("step"))
        reached = frame.withColumns({"upto": upto, "all": F.sum("n").over(whole)}).where(F.col("upto") >= quantile * F.col("all"))
        return reached.groupBy(*by).agg((F.exp(F.min("step") / STEPS) * margin).alias("threshold"), F.max("all").alias("documents"))

    overall = first_over(bins.groupBy("step").agg(F.sum("n").alias("n")), []).first()
    own = first_over(bins, ["lang"]).where(F.col("documents") >= MIN_CALIBRATION)
    return materialise(own.select("lang", "threshold"), "thresholds"), overall["threshold"] if overall else None


def _judged(docs: DataFrame, labels: DataFrame, keep: list[str], quantile: float, margin: float, order: int) -> DataFrame:
    """The kept columns under names of ``_place``, beside n_tokens, perplexity, threshold and kept, with which none of the input's can clash."""
    ids = trusted_ids(labels)
    trusted = docs.select("doc_id", "text").join(ids, "doc_id", "left_semi")
    model = estimate(counts(trusted.where(_fifth() > 0), order), order)
    places = {"doc_id": "doc_id", "lang": "lang", "text": "text"} | _places(keep)
    named = docs.select(*[F.col(f"`{c}`").alias(place) for c, place in places.items()])
    scored = losses(named, {"trusted": model}, [place for c, place in places.items() if c != "text" or c in keep])
    scored = materialise(scored.withColumn("perplexity", _perplexity()), "scored")
    # The trusted fifth that the model has not seen sets the limits.
    held = scored.where(_fifth() == 0).join(ids, "doc_id", "left_semi").select("lang", "perplexity")
    by_language, overall = thresholds(held, quantile, margin)
    small = by_language.count() <= BROADCAST_LANGUAGES
    limits = by_language.select(F.col("lang").alias("_lang"), F.col("threshold").alias("_own"))
    joined = scored.join(F.broadcast(limits) if small else limits, F.col("lang").eqNullSafe(F.col("_lang")), "left")
    joined = joined.withColumn("threshold", F.coalesce("_own", F.lit(overall).cast("double"), F.lit(256.5)))
    return joined.withColumn("kept", F.coalesce(F.col("perplexity") <= F.col("threshold"), F.lit(False)))


def _places(keep: list[str]) -> dict[str, str]:
    return {c: c if c in ("doc_id", "lang", "text") else f"keep_{i}" for i, c in enumerate(keep)}


def score(docs: DataFrame, labels: DataFrame, keep: list[str], quantile: float = QUANTILE, margin: float = MARGIN, order: int = ORDER) -> DataFrame:
    """The kept columns, n_tokens, perplexity, threshold and kept of every document."""
    judged = _judged(docs, labels, keep, quantile, margin, order)
    return judged.select(*[F.col(place).alias(c) for c, place in _places(keep).items()], "n_tokens", "perplexity", "threshold", "kept")


def accepted(docs: DataFrame, labels: DataFrame, quantile: float = QUANTILE, margin: float = MARGIN, order: int = ORDER) -> DataFrame:
    """The documents that are kept, with all their columns and no others."""
    judged = _judged(docs, labels, docs.columns, quantile, margin, order).where("kept")
    return judged.select(*[F.col(place).alias(c) for c, place in _places(docs.columns).items()])


def cross_entropy_difference(docs: DataFrame, labels: DataFrame, order: int = SELECTION_ORDER) -> DataFrame:
    """doc_id, n_tokens, loss_target, loss_background and score (their difference per token) of every document."""
    ids = trusted_ids(labels)
    source = docs.select("doc_id", "text")
    size = F.coalesce(F.sum(F.octet_length("text")), F.lit(0))
    target = source.join(ids, "doc_id", "left_semi")
    all_bytes, target_bytes = source.agg(size).first()[0], target.agg(size).first()[0]
    share = min(1.0, target_bytes / all_bytes) if all_bytes else 0.0
    place = F.pmod(F.xxhash64(F.lit("background"), "doc_id", F.col("text")), F.lit(1 << 40)) / float(1 << 40)
    models: dict[str, Model] = {"target": estimate(counts(target, order), order), "background": estimate(counts(source.where(place < share), order), order)}
    scored = losses(source, models, ["doc_id"])
    difference = F.when(F.col("n_tokens") > 0, (F.col("loss_target") - F.col("loss_background")) / F.col("n_tokens"))
    return scored.select("doc_id", "n_tokens", "loss_target", "loss_background", difference.alias("score"))
