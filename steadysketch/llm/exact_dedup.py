"""Exact duplicates through an extendible-hash index on shared files.

Texts are compared after replacing each run of ASCII white space by one space. A task first chains the
texts of its own rows by SHA-256, comparing bytes, so that one record for each distinct text of a task
goes on: key, text, ids of its rows. The records are written to bucket files in the shared folder. A
directory maps the leading bits of a key to a bucket; a bucket with more than ``capacity`` records, or with
more than CAPACITY_BYTES of text, is split by one more bit, the directory doubling when the bucket already uses all of its bits. A bucket is
a range of keys and has one owner task, which walks its records in key order, chains records of equal
key and compares their bytes; only one copy of each distinct text of the key at hand is held. Rows get
their group back by a join on record numbers, which are unique, so no group of copies meets in a task.

Defined results: null text counts as empty. The row with the smallest doc_id stays, a null id counting
as larger than any; of several such rows one stays. Repeated rows count each. Columns besides doc_id
and text are ignored.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterator

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..runtime import materialise, scratch_path
from .common import SPACE, map_batches, texts

#: Records and bytes of text of a bucket before it splits, and bits of a key that a directory may use.
CAPACITY, CAPACITY_BYTES = 25_000, 48_000_000
#: Bytes of texts and ids that a task holds before it hands its records on.
HELD = 64_000_000
MOST_BITS = 24
#: Keys with several records that are broadcast; more are joined by a shuffle.
BROADCAST_KEYS = 500_000

LOCAL = "record long, key binary, text binary, doc_ids array<long>, least long, n long"


def normalised(text: str | None) -> bytes:
    raw = (text or "").encode("utf-8", "surrogatepass")
    parts = raw.split()
    out = b" ".join(parts)
    if raw[:1].isspace():
        out = b" " + out
    if parts and raw[-1:].isspace():
        out += b" "
    return out


def _least(a: int | None, b: int | None) -> int | None:
    return b if a is None else a if b is None else min(a, b)


def local_records(docs: DataFrame, key_bits: int = 256) -> DataFrame:
    """One record for each distinct text of a task's rows. ``key_bits`` below 256 makes keys collide (for tests)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        number = TaskContext.get().partitionId() << 32
        held = 0
        chains: dict[bytes, list[list]] = {}

        def emit() -> Iterator[pa.RecordBatch]:
            nonlocal number
            rows = [(key, text, ids) for key, chain in chains.items() for text, ids in chain]
            for at in range(0, len(rows), 1000):
                keys, found, ids = zip(*rows[at : at + 1000])
                real = [[i for i in own if i is not None] for own in ids]
                yield pa.RecordBatch.from_arrays(
                    [
                        pa.array(range(number, number + len(keys)), pa.int64()), pa.array(keys, pa.binary()), pa.array(found, pa.binary()), pa.array(ids, pa.list_(pa.int64())),
                        pa.array([min(own, default=None) for own in real], pa.int64()), pa.array(list(map(len, ids)), pa.int64()),
                    ],
                    ["record", "key", "text", "doc_ids", "least", "n"],
                )
                number += len(keys)
            chains.clear()

        for batch in batches:
            for doc_id, text in zip(batch.column("doc_id").to_pylist(), batch.column("text").to_pylist()):
                text = normalised(text)
                key = hashlib.sha256(text).digest()
                if key_bits < 256:
                    key = (int.from_bytes(key) >> (256 - key_bits) << (256 - key_bits)).to_bytes(32)
                chain = chains.setdefault(key, [])
                for entry in chain:
                    if entry[0] == text:
                        entry[1].append(doc_id)
                        held += 8
                        break
                else:
                    chain.append([text, [doc_id]])
                    held += len(text) + 8
                if held > HELD:
                    yield from emit()
                    held = 0
        yield from emit()

    return map_batches(texts(docs), run, LOCAL, rows=500)


# -- directory ------------------------------------------------------------------------------------
class Directory:
    """Bucket of each prefix of ``depth`` bits; a bucket is its local depth and prefix."""

    def __init__(self, depth: int):
        self.base = self.depth = depth
        self.slots = [(depth, p) for p in range(1 << depth)]
        self.gone: list[tuple[int, int]] = []

    def split(self, bucket: tuple[int, int]) -> None:
        local, prefix = bucket
        if local == self.depth:
            self.slots = [b for b in self.slots for _ in range(2)]
            self.depth += 1
        wide = self.depth - local
        for slot in range(prefix << wide, (prefix + 1) << wide):
            self.slots[slot] = (local + 1, slot >> (wide - 1))
        self.gone.append(bucket)

    def buckets(self) -> int:
        return len(set(self.slots))

    def column(self, key: str = "key") -> Column:
        """Bucket number of a key: its leading bits at the first depth, one bit more for each split on its way."""
        lead = F.conv(F.substring(F.hex(key), 1, 8), 16, 10).cast("long")
        at = lambda depth: F.shiftright(lead, 32 - depth) + F.lit(depth << 32)
        out = at(self.base)
        for depth in range(self.base, self.depth):
            if parents := [number(b) for b in self.gone if b[0] == depth]:
                out = F.when(out.isin(parents), at(depth + 1)).otherwise(out)
        return out


def number(bucket: tuple[int, int]) -> int:
    return bucket[0] << 32 | bucket[1]


def build_index(records: DataFrame, capacity: int = CAPACITY, expected: int = 0, expected_bytes: int = 0) -> tuple[DataFrame, Directory]:
    """Write records to bucket files under the shared folder and split overfull buckets until none is left.

    Returns the stored records, with their bucket, and the directory. A bucket whose keys agree in all
    the bits that a directory may use stays as it is: its owner chains them.
    """
    spark = records.sparkSession
    folder = scratch_path(spark, "index")
    directory = Directory(min(MOST_BITS, max(0, math.ceil(math.log2(max(1, expected / capacity, expected_bytes / CAPACITY_BYTES))))))
    _write(records, directory, f"{folder}/round=0")
    rounds = 0
    while True:
        stored = spark.read.schema(LOCAL + ", round int, bucket long").parquet(folder)
        stored = stored.where(~F.col("bucket").isin([number(b) for b in directory.gone])) if directory.gone else stored
        kinds = F.count_distinct(F.substring("key", 1, MOST_BITS // 8))
        sizes = stored.groupBy("bucket").agg(F.count("*").alias("n"), F.sum(F.octet_length("text")).alias("bytes"), kinds.alias("kinds"))
        full = sizes.where(((F.col("n") > capacity) | (F.col("bytes") > CAPACITY_BYTES)) & (F.col("kinds") > 1))
        parents = [(b >> 32, b & 0xFFFFFFFF) for (b,) in full.select("bucket").collect()]
        if not parents:
            return stored.drop("round"), directory
        for bucket in parents:
            directory.split(bucket)
        rounds += 1
        _write(stored.where(F.col("bucket").isin([number(b) for b in parents])).drop("bucket", "round"), directory, f"{folder}/round={rounds}")


def _dealt(df: DataFrame, buckets: int) -> DataFrame:
    """Rows of a bucket together; more partitions than buckets, so that few tasks have two."""
    return df.repartition(3 * buckets, "bucket")


def _write(records: DataFrame, directory: Directory, path: str) -> None:
    _dealt(records.withColumn("bucket", directory.column()), directory.buckets()).write.partitionBy("bucket").parquet(path)


# -- owners ---------------------------------------------------------------------------------------
OWNED = "record long, chain int, keep_id long, group_size long, first long"


def _owner(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    key, chain = None, []
    out: list[tuple] = []

    def close() -> None:
        for spot, (_, members, least, n) in enumerate(chain):
            first = min((r for r, own in members if own == least), default=None)
            out.extend((record, spot, least, n, first) for record, _ in members)

    def batch_of() -> pa.RecordBatch:
        columns = [pa.array(c, t) for c, t in zip(zip(*out), (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64()))]
        return pa.RecordBatch.from_arrays(columns, ["record", "chain", "keep_id", "group_size", "first"])

    for batch in batches:
        for record, own, text, least, n in zip(*(batch.column(c).to_pylist() for c in ("record", "key", "text", "least", "n"))):
            if own != key:
                close()
                key, chain = own, []
                if len(out) > 10_000:
                    yield batch_of()
                    out.clear()
            for entry in chain:
                if entry[0] == text:
                    entry[1].append((record, least))
                    entry[2], entry[3] = _least(entry[2], least), entry[3] + n
                    break
            else:
                chain.append([text, [(record, least)], least, n])
    close()
    if out:
        yield batch_of()


def duplicates(docs: DataFrame, capacity: int = CAPACITY, key_bits: int = 256) -> DataFrame:
    """One row per document: doc_id, keep_id, group_size, kept, text_sha256 (of the normalised text) and chain."""
    source = texts(docs)
    rows, size = source.agg(F.count("*"), F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()
    stored, directory = build_index(local_records(source, key_bits), capacity, rows, size)
    digest = F.lower(F.hex("key")) if key_bits == 256 else F.sha2("text", 256)
    stored = stored.withColumn("text_sha256", digest)
    # Keys with one record are settled; only records of the others, few beside them, go to their owners.
    shared_keys = materialise(stored.groupBy("key").agg(F.count("*").alias("records")).where("records > 1").select("key"), "keys")
    if shared_keys.count() <= BROADCAST_KEYS:
        shared_keys = F.broadcast(shared_keys)
    alone = stored.join(shared_keys, "key", "left_anti")
    shared = stored.join(shared_keys, "key", "left_semi")
    owners = _dealt(shared.select("bucket", "record", "key", "text", "least", "n"), directory.buckets()).sortWithinPartitions("key", "record")
    owned = map_batches(owners.select("record", "key", "text", "least", "n"), _owner, OWNED, rows=500)
    columns = ["record", "text_sha256", "doc_ids", "chain", "keep_id", "group_size", "first"]
    rows = shared.select("record", "text_sha256", "doc_ids").join(owned, "record").select(columns)
    rows = rows.unionAll(alone.select("record", "text_sha256", "doc_ids", F.lit(0).alias("chain"), F.col("least").alias("keep_id"), F.col("n").alias("group_size"), F.col("record").alias("first")))
    rows = rows.select(*columns[:2], *columns[3:], F.array_position("doc_ids", F.col("keep_id")).alias("home"), F.posexplode("doc_ids").alias("at", "doc_id"))
    stays = (F.col("record") == F.col("first")) & (F.col("at") == F.when(F.col("keep_id").isNull(), 0).otherwise(F.col("home") - 1))
    return rows.select("doc_id", "keep_id", "group_size", F.coalesce(stays, F.lit(False)).alias("kept"), "text_sha256", "chain")


def keep_first(docs: DataFrame) -> DataFrame:
    """All columns of the rows that stay: one for each distinct normalised text.

    Rows are told apart by id and digest. What goes is joined, not what stays, so documents without
    copies are never shuffled while the list of what goes can be broadcast.
    """
    found = materialise(duplicates(docs).select(F.col("doc_id").alias("_id"), F.col("text_sha256").alias("_digest"), "kept"), "kept")
    rows = found.groupBy("_id", "_digest").agg(F.max("kept").alias("stays"), F.count("*").alias("n")).where("not stays or n > 1")
    rows = materialise(rows, "gone")
    rows = F.broadcast(rows) if rows.count() <= BROADCAST_KEYS else rows
    text = F.regexp_replace(F.coalesce("text", F.lit("")), SPACE, " ")
    marked = docs.withColumn("_digest_here", F.sha2(text, 256))
    same = docs["doc_id"].eqNullSafe(F.col("_id")) & (F.col("_digest_here") == F.col("_digest"))
    rest = marked.join(rows, same, "left_anti")
    again = marked.join(rows.where("stays"), same, "left_semi").dropDuplicates(["doc_id", "_digest_here"])
    return rest.unionAll(again).select(docs.columns)
