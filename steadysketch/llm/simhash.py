"""SimHash near-duplicates found through Golay-code keys.

Fingerprint: 64 bits of majority votes over the XXH64 values (seed 42) of a text's word shingles,
repeats included. Two fingerprints are linked if they differ in at most two bits.

Search: the 64 bits fall into segments of 22, 21 and 21 bits. Of three segments that share two errors
one is without any (pigeonhole), and each other has two at most. The perfect (23,12) Golay code covers
every word within distance 3; the codewords within distance 4 of a word are one or six, and two words
within distance 2 always have one of them in common (the codeword nearest to a word between the two
is within 4 of both). So a key is: which segment is error-free, its bits, and the index of a codeword
near the next segment. Linked fingerprints share at least one key, candidates are verified by counting
bits, and one row stands for all texts of equal fingerprint.

Buckets of a key with more than ``bucket`` distinct fingerprints emit no pairs. Their members get the
exact star keys instead: a fingerprint and its 64 one-bit neighbours. Two fingerprints have a star key
in common if and only if they differ in at most two bits, so a link of each to the smallest holder of
the key joins the same groups with 65 rows a fingerprint.

Defined results: null text counts as empty; texts without words have fingerprint zero and are linked
like any other; a null doc_id takes part and is never the smallest while another id is there; repeated
rows stay repeated; columns besides doc_id and text are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..runtime import materialise
from .common import map_batches, texts
from .components import components

#: Start bit and width of each segment.
SEGMENTS = ((0, 22), (22, 21), (43, 21))
#: Generator polynomial of the (23,12) Golay code.
GENERATOR = 0b110001110101
ERRORS = 2
#: Most distinct fingerprints of a key whose pairs are compared one by one.
BUCKET = 64
#: A fingerprint that more than one row in so many has is joined by broadcast.
HOT_SHARE = 1_000
#: Most rows to drop that are broadcast; more are joined by a shuffle.
BROADCAST_ROWS = 2_000_000

_TO_LOWER = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))


# -- fingerprints ---------------------------------------------------------------------------------
def fingerprint(text: str | None, size: int = 3) -> int:
    words = (text or "").encode("utf-8", "surrogatepass").translate(_TO_LOWER).split()
    if not words:
        return 0
    if len(words) < size:
        shingles = [b" ".join(words)]
    else:
        shingles = list(map(b" ".join, zip(*(words[i:] for i in range(size)))))
    digest = xxhash.xxh64_intdigest
    hashes = np.array([digest(s, 42) for s in shingles], np.uint64)
    votes = np.zeros(64, np.int64)
    for at in range(0, len(hashes), 1 << 16):
        part = hashes[at : at + (1 << 16)]
        votes += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(2 * votes > len(hashes), bitorder="little").view(np.uint64)[0])


def fingerprints(docs: DataFrame, size: int = 3) -> DataFrame:
    """(doc_id, fp, text_key) with the fingerprint as a signed 64-bit number; the key tells rows of one id apart."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = np.array([fingerprint(t, size) for t in batch.column("text").to_pylist()], np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id").cast(pa.int64()), pa.array(found, pa.int64()), batch.column("text_key")], ["doc_id", "fp", "text_key"])

    return map_batches(texts(docs).withColumn("text_key", F.xxhash64("text")), run, "doc_id long, fp long, text_key long")


# -- Golay code -----------------------------------------------------------------------------------
def _remainder(words: np.ndarray) -> np.ndarray:
    rest = words.copy()
    for bit in range(22, 10, -1):
        rest ^= np.where(rest >> bit & 1, GENERATOR << (bit - 11), 0)
    return rest


class Golay:
    """Indices of the codewords near a 23-bit word, found by its syndrome."""

    def __init__(self) -> None:
        bits = [1 << i for i in range(23)]
        low = [0] + bits + [a | b for i, a in enumerate(bits) for b in bits[:i]]
        three = [a | b for i, a in enumerate(bits) for j, b in enumerate(bits[:i]) for b in [b | c for c in bits[:j]]]
        four = np.array([a | b | c | d for i, a in enumerate(bits) for j, b in enumerate(bits[:i]) for k, c in enumerate(bits[:j]) for d in bits[:k]], np.int64)
        leaders = np.array(low + three, np.int64)
        #: Error patterns of weight up to 4 for each syndrome; -1 where a syndrome has one only.
        self.patterns = np.full((2048, 6), -1, np.int64)
        self.patterns[_remainder(leaders), 0] = leaders
        found = _remainder(four)
        order = np.argsort(found, kind="stable")
        found, four = found[order], four[order]
        rank = np.arange(len(found)) - np.searchsorted(found, found)
        self.patterns[found, rank + 1] = four

    def keys(self, words: np.ndarray) -> np.ndarray:
        """Per word six indices of codewords within distance 4, or one and five times -1."""
        patterns = self.patterns[_remainder(words)]
        return np.where(patterns >= 0, (words[:, None] ^ patterns) >> 11, -1)


def keys_of(fp: np.ndarray, golay: Golay) -> tuple[np.ndarray, np.ndarray]:
    """(row, key) for every key of every fingerprint."""
    bits = fp.view(np.uint64)
    parts = [(bits >> np.uint64(at) & np.uint64((1 << width) - 1)).astype(np.int64) for at, width in SEGMENTS]
    rows, keys = [], []
    for k in range(3):
        near = golay.keys(parts[(k + 1) % 3])
        row, spot = np.nonzero(near >= 0)
        rows.append(row)
        keys.append(k << 40 | parts[k][row] << 12 | near[row, spot])
    return np.concatenate(rows), np.concatenate(keys)


# -- links ----------------------------------------------------------------------------------------
def _explode_keys(fps: DataFrame) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        golay = Golay()
        for batch in batches:
            fp = batch.column("fp").to_numpy(zero_copy_only=False).astype(np.int64)
            rows, keys = keys_of(fp, golay)
            yield pa.RecordBatch.from_arrays([pa.array(keys), pa.array(fp[rows])], ["key", "fp"])

    return map_batches(fps.select("fp"), run, "key long, fp long", rows=10_000)


def apart(a: str | Column, b: str | Column) -> Column:
    left, right = (F.col(x) if isinstance(x, str) else x for x in (a, b))
    return F.bit_count(left.bitwiseXOR(right))


def links(fps: DataFrame, bucket: int = BUCKET) -> DataFrame:
    """(a, b): links between distinct fingerprints whose components are those of all pairs within two bits."""
    # Keys are counted before anything of theirs meets, so that no task ever holds a crowded bucket.
    sizes = _explode_keys(fps).groupBy("key").agg(F.count("*").alias("n")).where("n > 1")
    held = materialise(_explode_keys(fps).join(sizes, "key"), "buckets")
    later = Window.partitionBy("key").orderBy("fp").rowsBetween(1, bucket)
    paired = held.where(F.col("n") <= bucket).select("fp", F.collect_list("fp").over(later).alias("later"))
    close = paired.select("fp", F.explode("later").alias("other")).where(apart("fp", "other") <= ERRORS)
    crowded = held.where(F.col("n") > bucket).select("fp").distinct()
    around = F.concat(F.array(F.col("fp")), F.transform(F.sequence(F.lit(0), F.lit(63)), lambda i: F.col("fp").bitwiseXOR(F.call_function("shiftleft", F.lit(1).cast("long"), i))))
    star = crowded.select("fp", F.explode(around).alias("key"))
    hubs = star.groupBy("key").agg(F.min("fp").alias("other"), F.count("*").alias("n")).where("n > 1").select("key", "other")
    joined = star.join(hubs, "key").where("fp <> other").select("fp", "other")
    return close.unionAll(joined).select(F.col("fp").alias("a"), F.col("other").alias("b")).distinct()


def near_duplicates(docs: DataFrame, size: int = 3, bucket: int = BUCKET) -> DataFrame:
    """One row per document: doc_id, fingerprint (16 hex digits), component_id (smallest doc_id reachable) and text_key."""
    rows = materialise(fingerprints(docs, size), "fingerprints")
    fps = materialise(rows.groupBy("fp").agg(F.min("doc_id").alias("least"), F.count("*").alias("n")), "distinct")
    roots = components(links(fps, bucket))
    grouped = fps.join(roots.withColumnRenamed("node", "fp"), "fp").select("fp", "least", "root")
    own = fps.join(roots.select(F.col("root").alias("fp")).distinct(), "fp").select("fp", "least", F.col("fp").alias("root"))
    members = grouped.unionAll(own)
    smallest = members.groupBy("root").agg(F.min("least").alias("component_id"))
    moved = members.join(smallest, "root").select("fp", "component_id")
    total = rows.count()
    labels = materialise(fps.join(moved, "fp", "left").select("fp", F.coalesce("component_id", "least").alias("component_id"), (F.col("n") * HOT_SHARE > total).alias("hot")), "labels")
    # A fingerprint of more than one in HOT_SHARE rows is broadcast: there are fewer than HOT_SHARE of them.
    hot, cold = F.broadcast(labels.where("hot").drop("hot")), labels.where(~F.col("hot")).drop("hot")
    named = rows.join(hot, "fp").unionByName(rows.join(hot.select("fp"), "fp", "left_anti").join(cold, "fp"))
    return named.select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id", "text_key")


def keep_one(docs: DataFrame, size: int = 3) -> DataFrame:
    """All columns of one document for each component: the one with the smallest id, once if its row repeats. Rows without an id stay."""
    found = materialise(near_duplicates(docs, size).where("component_id is not null").select(F.col("doc_id").alias("_id"), F.col("text_key").alias("_key"), "component_id"), "near")
    first = found.where("_id = component_id").groupBy("component_id").agg(F.min("_key").alias("_first"))
    stays = (F.col("_id") == F.col("component_id")) & (F.col("_key") == F.col("_first"))
    rows = found.where("_id is not null").join(first.select("component_id", "_first"), "component_id").groupBy("_id", "_key").agg(F.max(stays).alias("stays"), F.count("*").alias("n"))
    rows = materialise(rows.where("not stays or n > 1").select("_id", "_key", "stays"), "gone")
    rows = F.broadcast(rows) if rows.count() <= BROADCAST_ROWS else rows
    marked = docs.withColumn("_key_here", F.xxhash64("text"))
    same = (docs["doc_id"] == F.col("_id")) & (F.col("_key_here") == F.col("_key"))
    rest = marked.join(rows, same, "left_anti")
    again = marked.join(rows.where("stays"), same, "left_semi").dropDuplicates(["doc_id", "_key_here"])
    return rest.unionAll(again).select(docs.columns)
