"""Interpolated modified Kneser-Ney models over bytes, counted, joined and applied in shards.

The tokens are the bytes of the UTF-8 text, so every model has the same vocabulary of 256 tokens and no
unknown ones. An n-gram is packed into 64 bits, eight a token, with the begin mark 255 (no UTF-8 byte)
in place of what precedes a text.

Counting: a task folds the n-grams of its own texts into distinct ones with counts before anything is
shuffled. Estimation: the count of an n-gram of the highest order is how often it occurs, of a lower
order how many distinct tokens precede it; three discounts per order follow from the numbers of n-grams
counted once to four times. Totals of each context are joined to its n-grams, and the probability of
order k is joined to that of order k - 1 by the n-gram's suffix, each join being sharded by the hash of
its key. Order 0 is uniform.

Application: a task reads its documents in groups of a bounded size and hands on the distinct n-grams of
each group. All distinct n-grams asked for are joined, by the n-gram and then by ever shorter ones of its
suffixes and contexts, with the sharded tables of all models, which gives each its -ln p; that is joined
back to the groups, and every group adds up the losses of its documents. No table passes through the
driver or is broadcast, but for the two lowest orders, which cannot have more than 65 792 n-grams.
"""

from __future__ import annotations

import gc
import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..runtime import bounded_batches, discard, materialise, ship
from .common import begin, give_back, give_back_later, map_batches

ORDER = 5
BEGIN = 255
#: Distinct n-grams of pieces folded at a time, bytes of text of the documents of a group, and of a piece of a text.
FOLD, GROUP, PIECE = 1_000_000, 32_000_000, 1 << 20
#: Level at which the documents of a group are compressed on their way.
LEVEL = 6
#: Orders whose tables are bounded by the 256 tokens (256 + 256^2 n-grams) and so may be broadcast.
BOUNDED_ORDERS = 2
#: Least weight of a lower order when a loss is taken: small training texts can have no discount at all.
FLOOR = 1e-12
MULTIPLIER = 0x9E3779B97F4A7C15


# -- n-grams of texts -----------------------------------------------------------------------------
def packed(raw: bytes, order: int) -> np.ndarray:
    """For each byte of a text the n-gram of ``order`` tokens that ends with it."""
    tokens = np.frombuffer(b"\xff" * (order - 1) + raw, np.uint8)
    n = len(raw)
    out = tokens[:n].astype(np.int64)
    for i in range(1, order):
        out <<= 8
        out |= tokens[i : i + n]
    return out


def pieces(raws: list[bytes], order: int, most: int = PIECE) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """The n-grams of texts with the position of their text, about ``most`` at a time: short texts together, long ones cut."""
    grams, owners, held = [], [], 0
    for at, raw in enumerate(raws):
        for a in range(0, len(raw), most):
            before = raw[max(0, a - order + 1) : a]
            part = packed(before + raw[a : a + most], order)[len(before) :]
            grams.append(part)
            owners.append((at, len(part)))
            held += len(part)
            if held >= most:
                yield np.concatenate(grams), np.repeat(*map(np.array, zip(*owners)))
                grams, owners, held = [], [], 0
    if grams:
        yield np.concatenate(grams), np.repeat(*map(np.array, zip(*owners)))


def distinct(grams: np.ndarray, weights: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Distinct n-grams, ascending, with counts or sums of weights."""
    if weights is None:
        grams = np.sort(grams)
    else:
        order = np.argsort(grams, kind="stable")
        grams, weights = grams[order], weights[order]
    first = np.nonzero(np.concatenate(([True], grams[1:] != grams[:-1])))[0] if len(grams) else np.empty(0, np.int64)
    n = np.diff(np.append(first, len(grams))) if weights is None or not len(grams) else np.add.reduceat(weights, first)
    return grams[first], n


def counts(docs: DataFrame, order: int = ORDER, text: str = "text") -> DataFrame:
    """(gram, n) over all the whole texts; null and empty texts have none."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size = [(np.empty(0, np.int64), np.empty(0, np.int64))], 0

        def fold() -> None:
            nonlocal size
            grams, n = map(np.concatenate, zip(*held))
            held[:] = [distinct(grams, n)]
            size = 0

        for batch in batches:
            for part, _ in pieces([value.encode("utf-8", "surrogatepass") for value in batch.column("text").to_pylist() if value], order):
                held.append(distinct(part))
                size += len(held[-1][0])
                if size > FOLD:
                    fold()
        fold()
        grams, n = held[0]
        for at in range(0, len(grams), 100_000):
            yield pa.RecordBatch.from_arrays([pa.array(grams[at : at + 100_000]), pa.array(n[at : at + 100_000])], ["gram", "n"])

    return map_batches(docs.select(F.col(text).alias("text")), run, "gram long, n long", rows=500).groupBy("gram").agg(F.sum("n").alias("n"))


# -- estimation -----------------------------------------------------------------------------------
def _suffix(order: int) -> Column:
    """An n-gram without its first token."""
    return F.col("gram").bitwiseAND(F.lit((1 << 8 * (order - 1)) - 1))


def _context(gram: str = "gram") -> Column:
    return F.shiftright(gram, 8)


def discounts(tallies: dict[int, int]) -> tuple[float, float, float]:
    """The three discounts of an order from how many of its n-grams are counted once, twice, ... four times."""
    n1, n2, n3, n4 = (tallies.get(k, 0) for k in (1, 2, 3, 4))
    y = n1 / (n1 + 2 * n2) if n1 + n2 else 0.0
    out = []
    for k, (a, b) in enumerate(((n1, n2), (n2, n3), (n3, n4)), 1):
        out.append(min(float(k), max(0.0, k - (k + 1) * y * b / a)) if a else y)
    return out[0], out[1], out[2]


@dataclass
class Model:
    """n-gram tables of all orders: (k, gram, p, backoff), the backoff being the weight of order k for the context ``gram``."""

    table: DataFrame
    order: int

    def size(self) -> int:
        return self.table.count()


def estimate(grams: DataFrame, order: int = ORDER) -> Model:
    """Modified Kneser-Ney from (gram, n) of the highest order.

    ``table`` has a row for each n-gram seen, of every order k, with its interpolated probability, and
    the row of a context has the backoff weight of what follows it. An empty training set gives the
    uniform model.
    """
    by_order = {order: materialise(grams, "grams")}
    for k in range(order - 1, 0, -1):
        by_order[k] = materialise(by_order[k + 1].select(_suffix(k + 1).alias("gram")).groupBy("gram").agg(F.count("*").alias("n")), "grams")
    stacked = None
    for k, frame in by_order.items():
        part = frame.select(F.lit(k).alias("k"), "gram", "n")
        stacked = part if stacked is None else stacked.unionAll(part)
    tallies: dict[int, dict[int, int]] = {k: {} for k in by_order}
    for k, n, c in stacked.where("n <= 4").groupBy("k", "n").count().collect():
        tallies[k][n] = c
    cut = {k: discounts(t) for k, t in tallies.items()}

    def discount(k: Column, n: Column) -> Column:
        out = F.lit(0.0)
        for order_, d in cut.items():
            out = F.when(k == order_, F.when(n == 1, d[0]).when(n == 2, d[1]).otherwise(d[2])).otherwise(out)
        return out

    less = stacked.withColumn("d", discount(F.col("k"), F.col("n"))).withColumn("context", _context())
    totals = materialise(less.groupBy("k", "context").agg(F.sum("n").alias("total"), F.sum("d").alias("kept_back")).withColumn("backoff", F.col("kept_back") / F.col("total")), "contexts")
    below, tables = None, []
    for k in range(1, order + 1):
        own = less.where(F.col("k") == k).join(totals.where(F.col("k") == k).select("context", "total", "backoff"), "context")
        if below is None:
            lower = own.withColumn("lower", F.lit(1 / 256))
        else:
            lower = own.withColumn("tail", _suffix(k)).join(below.select(F.col("gram").alias("tail"), F.col("p").alias("lower")), "tail")
        p = (F.col("n") - F.col("d")) / F.col("total") + F.col("backoff") * F.col("lower")
        below = materialise(lower.select("gram", p.alias("p")), "probabilities")
        tables.append(below.select(F.lit(k).alias("k"), "gram", F.col("p").alias("value")))
        # The weight of order k belongs to its context, an n-gram of order k - 1.
        tables.append(totals.where(F.col("k") == k).select((-F.col("k")).alias("k"), F.col("context").alias("gram"), F.col("backoff").alias("value")))
    out = tables[0]
    for more in tables[1:]:
        out = out.unionAll(more)
    for frame in by_order.values():
        discard(frame)
    return Model(out, order)


# -- application ----------------------------------------------------------------------------------
class Places:
    """Open-addressing table from distinct int64 keys to their places, looked up for whole arrays."""

    def __init__(self, keys: np.ndarray):
        self.bits = max(4, (2 * len(keys)).bit_length())
        self.mask = (1 << self.bits) - 1
        self.keys = np.full(1 << self.bits, -1, np.int64)
        self.places = np.full(1 << self.bits, -1, np.int32)
        todo, slots = np.arange(len(keys)), self._slots(keys)
        while len(todo):
            _, first = np.unique(slots, return_index=True)
            first = first[self.keys[slots[first]] == -1]
            self.keys[slots[first]], self.places[slots[first]] = keys[todo[first]], todo[first]
            left = np.ones(len(todo), bool)
            left[first] = False
            todo, slots = todo[left], slots[left] + 1 & self.mask

    def _slots(self, keys: np.ndarray) -> np.ndarray:
        return (keys.view(np.uint64) * np.uint64(MULTIPLIER) >> np.uint64(64 - self.bits)).view(np.int64)

    def of(self, keys: np.ndarray) -> np.ndarray:
        """Places of keys, -1 for those that are not there."""
        slots = self._slots(keys)
        found = self.keys[slots]
        out = np.where(found == keys, self.places[slots], -1)
        todo = np.nonzero((found != keys) & (found != -1))[0]
        while len(todo):
            slots[todo] = slots[todo] + 1 & self.mask
            found = self.keys[slots[todo]]
            hit = found == keys[todo]
            out[todo[hit]] = self.places[slots[todo[hit]]]
            todo = todo[(found != keys[todo]) & (found != -1)]
        return out


def groups(batches: Iterator[pa.RecordBatch], size: int) -> Iterator[tuple[pa.RecordBatch, list[bytes], int | None]]:
    """Slices of consecutive documents with their texts; the slice that ends a group has the name that the group's texts give.

    The texts of a group have ``size`` bytes together. Where batches end makes no difference to it, and nothing of a
    group is held here but the slice at hand.
    """
    held, name, last = 0, xxhash.xxh3_64(), None
    for batch in batches:
        first, raws = 0, []
        for at, text in enumerate(batch.column("text").to_pylist()):
            raw = text.encode("utf-8", "surrogatepass") if text else b""
            raws.append(raw)
            held += len(raw)
            name.update(len(raw).to_bytes(8))
            name.update(raw)
            if held >= size:
                yield batch.slice(first, at + 1 - first), raws, name.intdigest() >> 1
                raws, first, held, name, last = [], at + 1, 0, xxhash.xxh3_64(), None
        if raws:
            last = batch.slice(0, 0)
            yield batch.slice(first), raws, None
    if last is not None:
        yield last, [], name.intdigest() >> 1


def asked(docs: DataFrame, order: int, size: int = GROUP) -> DataFrame:
    """(grp, gram): the distinct n-grams of each group of documents."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found, more = [np.empty(0, np.int64)], 0
        for _, raws, name in groups(batches, size):
            for part, _ in pieces(raws, order):
                found.append(distinct(part)[0])
                more += len(found[-1])
                if more > FOLD:
                    found, more = [distinct(np.concatenate(found))[0]], 0
            if name is not None:
                grams = distinct(np.concatenate(found))[0]
                found, more = [np.empty(0, np.int64)], 0
                for at in range(0, len(grams), 100_000):
                    part = pa.array(grams[at : at + 100_000])
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(part), name)), part], ["grp", "gram"])

    return map_batches(docs, run, "grp long, gram long", rows=500)


def bundled(docs: DataFrame, keep: list[str], size: int = GROUP) -> DataFrame:
    """(grp, rows): the documents of each group, compressed, in a row for each slice, so that no row is as large as a group."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.Buffer] = []
        for rows, _, name in groups(batches, size):
            if rows.num_rows:
                sink = pa.BufferOutputStream()
                with pa.ipc.new_stream(sink, rows.schema, options=pa.ipc.IpcWriteOptions(compression=pa.Codec("zstd", LEVEL))) as out:
                    out.write_batch(rows)
                held.append(sink.getvalue())
            if name is not None:
                for one in held:
                    ends = pa.array([0, one.size], pa.int32()).buffers()[1]
                    yield pa.RecordBatch.from_arrays([pa.array([name]), pa.Array.from_buffers(pa.binary(), 1, [None, ends, one])], ["grp", "rows"])
                held.clear()

    return map_batches(docs, run, "grp long, rows binary", rows=500)


def gram_losses(grams: DataFrame, models: dict[str, Model]) -> DataFrame:
    """(gram, loss_<name>...): -ln p of distinct n-grams of the highest order, by joins with the tables of all models.

    Each level joins what is still open in some model with the n-grams of order k and the weights of their
    contexts, so only n-grams that no table has so far go on to the next. The keys of a side are distinct,
    so no key is hot.
    """
    (order,) = {m.order for m in models.values()}
    stacked = None
    for i, model in enumerate(models.values()):
        part = model.table.withColumn("m", F.lit(i))
        stacked = part if stacked is None else stacked.unionAll(part)
    wide = materialise(stacked.groupBy("k", "gram").agg(*[F.max(F.when(F.col("m") == i, F.col("value"))).alias(f"v{i}") for i in range(len(models))]), "tables")
    each = range(len(models))
    rows = grams.select("gram", *[F.lit(0.0).alias(f"l{i}") for i in each], *[F.lit(True).alias(f"open{i}") for i in each])
    settled: list[DataFrame] = []
    names = ["gram", *[f"l{i}" for i in each]]

    def side(k: int, key: str, prefix: str) -> DataFrame:
        out = wide.where(F.col("k") == k).select(F.col("gram").alias(key), *[F.col(f"v{i}").alias(f"{prefix}{i}") for i in each])
        return F.broadcast(out) if abs(k) <= BOUNDED_ORDERS else out

    for k in range(order, 0, -1):
        own = F.col("gram").bitwiseAND(F.lit((1 << 8 * k) - 1))
        found = rows.withColumns({"own": own, "context": F.shiftright(own, 8)}).join(side(k, "own", "p"), "own", "left").join(side(-k, "context", "b"), "context", "left")
        here = lambda i: F.when(~F.col(f"open{i}"), 0.0).otherwise(-F.log(F.greatest(F.coalesce(f"p{i}", f"b{i}", F.lit(1.0)), F.lit(FLOOR))))
        rows = found.select("gram", *[(F.col(f"l{i}") + here(i)).alias(f"l{i}") for i in each], *[(F.col(f"open{i}") & F.col(f"p{i}").isNull()).alias(f"open{i}") for i in each])
        still = F.greatest(*[F.col(f"open{i}") for i in each], F.lit(False))
        if k > BOUNDED_ORDERS:
            rows = materialise(rows, "level")
            settled.append(rows.where(~still).select(names))
            rows = rows.where(still)
    last = F.log(F.lit(256.0))
    settled.append(rows.select("gram", *[(F.col(f"l{i}") + F.when(F.col(f"open{i}"), last).otherwise(0.0)).alias(f"l{i}") for i in each]))
    out = settled[0]
    for more in settled[1:]:
        out = out.unionAll(more)
    return out.select("gram", *[F.col(f"l{i}").alias(f"loss_{name}") for i, name in enumerate(models)])


def losses(docs: DataFrame, models: dict[str, Model], keep: list[str], size: int = GROUP) -> DataFrame:
    """The kept columns of each document, n_tokens, and for each named model the sum of -ln p over its tokens.

    ``docs`` gives the same rows whenever it is read, as files do; a group whose n-grams are not those that
    were asked for stops the job. What a task holds is a group of documents and its distinct n-grams. A null
    or empty text has no tokens and losses of 0.
    """
    (order,) = {m.order for m in models.values()}
    spark, names = docs.sparkSession, list(models)
    wanted = docs.select(*keep, *([] if "text" in keep else ["text"]))
    fields = [docs.schema[c] for c in keep]
    schema = ", ".join([f"`{f.name}` {f.dataType.simpleString()}" for f in fields] + ["n_tokens long"] + [f"loss_{m} double" for m in names])
    scored = gram_losses(counts(docs, order).select("gram"), models)
    # Four bytes a loss are enough for sums of them and halve what goes back to the groups.
    scored = scored.select("gram", *[F.col(f"loss_{m}").cast("float").alias(f"loss_{m}") for m in names])
    by_group = asked(wanted, order, size).join(scored, "gram")

    def of_group(left: pa.Table, right: pa.Table) -> pa.Table:
        begin()
        gc.disable()
        out = list(scored_rows(left, right))
        gc.enable()
        give_back()
        give_back_later()
        # Their batches stay apart, so no one of them is as large as a group.
        return pa.Table.from_batches(out)

    def scored_rows(left: pa.Table, right: pa.Table) -> Iterator[pa.RecordBatch]:
        places = Places(np.ascontiguousarray(right.column("gram").to_numpy()))
        values = [right.column(f"loss_{m}").to_numpy().astype(np.float64) for m in names]
        for bundle in left.column("rows"):
            for rows in pa.ipc.open_stream(bundle.as_buffer()):
                raws = [t.encode("utf-8", "surrogatepass") if t else b"" for t in rows.column("text").to_pylist()]
                sums = np.zeros((len(names), len(raws)))
                for grams, owner in pieces(raws, order):
                    at = places.of(grams)
                    if (at < 0).any():
                        raise RuntimeError("the documents are not the same at each reading; write them to files first")
                    for total, value in zip(sums, values):
                        total += np.bincount(owner, value[at], len(raws))
                columns = [rows.column(c) for c in keep] + [pa.array(list(map(len, raws)), pa.int64()), *map(pa.array, sums)]
                yield pa.RecordBatch.from_arrays(columns, [*keep, "n_tokens", *[f"loss_{m}" for m in names]])

    ship(spark)
    bounded_batches(spark, 500)
    return bundled(wanted, keep, size).groupBy("grp").cogroup(by_group.groupBy("grp")).applyInArrow(of_group, schema)
