"""Language identification by rank-order profiles of character n-grams.

A profile is the list of the most frequent n-grams (one to three code points of lower-cased letters,
any run of other characters being one blank) of all training text of a language. A document's own
list is compared with each profile by the sum, over the document's n-grams, of how many places each
is out of its place, an n-gram the profile lacks counting as the profile's full length. The nearest
profile wins, ties going to the smaller name. The score is one minus that distance over the largest
possible one.

Defined results: a null text, or one without letters, is ``und`` with score 0, as is every text when
nothing could be learned. Rows with a null language or text teach nothing. A null doc_id counts as
the empty string in the split.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import map_batches

#: Length of profiles and of a document's list.
PLACES = 300
#: Training documents of one language (a bound on the fit, taken by a hash of the id).
PROFILE_DOCS = 8_000
#: Most languages whose profiles are sent to every worker.
MAX_LANGUAGES = 4_096

SCHEMA = "doc_id long, held_out boolean, lang_pred string, score double"
_letters: list[np.ndarray] = []


def held_out(doc_id: str = "doc_id") -> Column:
    return F.crc32(F.coalesce(F.col(doc_id).cast("string"), F.lit(""))) % 3 == 1


def _letter_codes() -> np.ndarray:
    """Code point + 2 of letters, 1 for all else."""
    if not _letters:
        codes = np.ones(0x110000, np.int64)
        for c in range(0x110000):
            if chr(c).isalpha():
                codes[c] = c + 2
        _letters.append(codes)
    return _letters[0]


def ngrams(text: str) -> np.ndarray:
    """Packed n-grams of a text, repeats included: 21 bits a character."""
    raw = np.frombuffer(text.lower().encode("utf-32-le", "surrogatepass"), np.uint32)
    codes = np.concatenate(([1], _letter_codes()[raw], [1]))
    blank = codes == 1
    codes = codes[~(blank & np.concatenate(([False], blank[:-1])))]
    one = codes[1:-1]
    two = codes[:-1] << 21 | codes[1:]
    three = two[:-1] << 21 | codes[2:]
    return np.concatenate((one[one > 1], two, three[one > 1])) if len(codes) > 2 else np.empty(0, np.int64)


def counted(grams: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct n-grams in ascending order, and how often each occurs."""
    grams = np.sort(grams)
    first = np.nonzero(np.concatenate(([True], grams[1:] != grams[:-1])))[0] if len(grams) else np.empty(0, np.int64)
    return grams[first], np.diff(np.append(first, len(grams)))


def ranked(text: str | None, places: int = PLACES) -> np.ndarray:
    """A document's most frequent n-grams, most frequent first, ties by code."""
    grams, n = counted(ngrams(text)) if text else (np.empty(0, np.int64),) * 2
    return grams[np.argsort(-n, kind="stable")[:places]]


def training_counts(docs: DataFrame, per_language: int = PROFILE_DOCS) -> DataFrame:
    """(lang, gram, n) over at most about ``per_language`` documents of each language."""
    rows = docs.select("doc_id", "text", "lang").where(F.col("lang").isNotNull() & F.col("text").isNotNull() & ~held_out())
    sizes = rows.groupBy("lang").agg(F.count("*").alias("rows_of_lang"))
    share = F.lit(float(per_language)) / F.col("rows_of_lang")
    place = F.pmod(F.xxhash64("doc_id"), F.lit(1 << 30)) / float(1 << 30)
    chosen = rows.join(F.broadcast(sizes.limit(MAX_LANGUAGES + 1)), "lang").where(place < share).select("lang", "text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[str, list[np.ndarray]] = {}
        total: dict[str, tuple[np.ndarray, np.ndarray]] = {}

        def fold(lang: str) -> None:
            grams, n = counted(np.concatenate(held.pop(lang)))
            if lang in total:
                all_grams, at = np.unique(np.concatenate((total[lang][0], grams)), return_inverse=True)
                grams, n = all_grams, np.bincount(at, np.concatenate((total[lang][1], n))).astype(np.int64)
            total[lang] = grams, n

        for batch in batches:
            for lang, text in zip(batch.column("lang").to_pylist(), batch.column("text").to_pylist()):
                held.setdefault(lang, []).append(ngrams(text))
            for lang in [k for k, v in held.items() if sum(map(len, v)) > 2_000_000]:
                fold(lang)
        for lang in list(held):
            fold(lang)
        for lang, (grams, n) in total.items():
            yield pa.RecordBatch.from_arrays([pa.array([lang] * len(grams), pa.string()), pa.array(grams), pa.array(n, pa.int64())], ["lang", "gram", "n"])

    return map_batches(chosen, run, "lang string, gram long, n long").groupBy("lang", "gram").agg(F.sum("n").alias("n"))


def learn_profiles(docs: DataFrame, places: int = PLACES, per_language: int = PROFILE_DOCS) -> list[tuple[str, np.ndarray]]:
    """(language, n-grams by place) for each language in order of name; at most MAX_LANGUAGES x places numbers reach the driver."""
    place = F.row_number().over(Window.partitionBy("lang").orderBy(F.desc("n"), "gram"))
    rows = training_counts(docs, per_language).withColumn("place", place).where(F.col("place") <= places)
    found: dict[str, list[tuple[int, int]]] = {}
    for lang, gram, at in rows.select("lang", "gram", "place").collect():
        found.setdefault(lang, []).append((at, gram))
    if len(found) > MAX_LANGUAGES:
        raise ValueError(f"{len(found)} languages; the profiles of at most {MAX_LANGUAGES} are sent to the workers")
    return [(lang, np.array([g for _, g in sorted(found[lang])], np.int64)) for lang in sorted(found)]


class Matcher:
    def __init__(self, profiles: list[tuple[str, np.ndarray]], places: int = PLACES):
        self.names, self.places = [name for name, _ in profiles], places
        grams = np.unique(np.concatenate([g for _, g in profiles])) if profiles else np.empty(0, np.int64)
        self.grams = np.append(grams, np.int64(-1))
        self.place = np.full((len(grams) + 1, len(profiles)), -1, np.int64)
        for k, (_, own) in enumerate(profiles):
            self.place[np.searchsorted(grams, own), k] = np.arange(len(own))
        self.known = len(grams)

    def match(self, text: str | None) -> tuple[str, float]:
        own = ranked(text, self.places)
        if not len(own) or not self.names:
            return "und", 0.0
        at = np.searchsorted(self.grams[:-1], own)
        at = np.where(self.grams[at] == own, at, self.known)
        place = self.place[at]
        apart = np.where(place < 0, self.places, np.abs(place - np.arange(len(own))[:, None])).sum(axis=0)
        best = int(np.argmin(apart))
        return self.names[best], float(max(0.0, 1 - apart[best] / (self.places * len(own))))


def identify(docs: DataFrame, profiles: list[tuple[str, np.ndarray]], places: int = PLACES) -> DataFrame:
    """Predict the language of every whole text: one narrow pass with the profiles broadcast."""
    shared = docs.sparkSession.sparkContext.broadcast(profiles)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        matcher = Matcher(shared.value, places)
        for batch in batches:
            found = [matcher.match(t) for t in batch.column("text").to_pylist()]
            columns = [batch.column("doc_id").cast(pa.int64()), batch.column("held_out"), pa.array([f[0] for f in found], pa.string()), pa.array([f[1] for f in found], pa.float64())]
            yield pa.RecordBatch.from_arrays(columns, ["doc_id", "held_out", "lang_pred", "score"])

    return map_batches(docs.select("doc_id", "text", held_out().alias("held_out")), run, SCHEMA)
