"""Nearest neighbours by additive quantisation.

A vector is approximated by the sum of one entry from each of several codebooks of full dimension. The
codebooks start as those of repeated k-means on residuals over a bounded sample and are then refitted
together by least squares to the codes that beam search gives the sample. The index has a row for each
distinct vector: its smallest ids, the vector, its code by beam search and the norm of its approximation.

Search runs in blocks of distinct query vectors against the whole index: a lookup table holds each query's
product with each codebook entry, so the approximate distance of a row is a sum of looked-up values and
its stored norm. A query has one budget for the whole table: a task hands on its ``rerank`` best by codes,
the best ``rerank`` of all tasks are joined to their vectors and measured exactly, and nothing else is.
So neither batches nor partitions change what is found.

Defined results: vectors that are null, zero, or hold nulls or non-finite components take no part, nor
do rows with a null id or with a dimension other than the commonest; a query is never its own candidate
(by id); rows that repeat an id are candidates each, of repeated query ids one is searched; fewer than
``k`` candidates give as many rows; ties go to the smaller id; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..runtime import discard, materialise
from .common import map_batches

BOOKS, ENTRIES, BEAM = 16, 256, 4
#: Rows that the codebooks are fitted on, at most about this many, taken by a hash of the id.
SAMPLE = 12_000
#: Rows of a batch, exact measurements per query in the whole table, distinct query vectors of a block.
BATCH, RERANK, BLOCK = 4_096, 1_024, 2_048
#: Rows of the index that a task goes through, so that what it hands on is a small share of them, and the fewest
#: queries for which it does so where there are more cores than such tasks.
ROWS, SHARE = 1_000_000, 256


@dataclass
class Quantiser:
    books: np.ndarray  # (books, entries, dimension)

    def encode(self, x: np.ndarray, beam: int = BEAM) -> tuple[np.ndarray, np.ndarray]:
        """Codes (n, books) and approximations of the rows of x, by beam search."""
        m, k, d = self.books.shape
        n = len(x)
        codes = np.zeros((n, 1, m), np.uint8 if k <= 256 else np.int32)
        rest = x[:, None, :].astype(np.float32)
        rows = np.arange(n)[:, None]
        for j in range(m):
            book = self.books[j]
            width = rest.shape[1]
            cost = (rest**2).sum(-1)[..., None] - 2 * (rest.reshape(-1, d) @ book.T).reshape(n, width, k) + (book**2).sum(-1)
            keep = 1 if j == m - 1 else min(beam, width * k)
            flat = cost.reshape(n, -1)
            best = flat.argmin(1)[:, None] if keep == 1 else np.argpartition(flat, keep - 1, axis=1)[:, :keep]
            beams, entry = best // k, best % k
            codes = codes[rows, beams]
            codes[..., j] = entry
            rest = rest[rows, beams] - book[entry]
        return codes[:, 0], x - rest[:, 0]


def _means(x: np.ndarray, k: int, rng: np.random.Generator, rounds: int = 8) -> np.ndarray:
    centres = x[rng.choice(len(x), k, replace=len(x) < k)].copy()
    for _ in range(rounds):
        near = ((centres**2).sum(1) - 2 * x @ centres.T).argmin(1)
        size = np.bincount(near, minlength=k)
        centres[size > 0] = _sums(x, near, k)[size > 0] / size[size > 0, None]
    return centres


def _sums(x: np.ndarray, group: np.ndarray, groups: int) -> np.ndarray:
    """Sums of the rows of x by group."""
    return np.stack([np.bincount(group, column, groups) for column in x.T], axis=1)


def fit(x: np.ndarray, books: int = BOOKS, entries: int = ENTRIES, rounds: int = 2, seed: int = 7) -> Quantiser:
    rng = np.random.default_rng(seed)
    x = x.astype(np.float32)
    entries = max(1, min(entries, len(x) // 4))
    rest, made = x.copy(), []
    for _ in range(books):
        book = _means(rest, entries, rng)
        rest = rest - book[((book**2).sum(1) - 2 * rest @ book.T).argmin(1)]
        made.append(book)
    quantiser = Quantiser(np.stack(made))
    for _ in range(rounds):
        parts = [quantiser.encode(x[a : a + BATCH])[0] for a in range(0, len(x), BATCH)]
        spots = np.concatenate(parts).astype(np.int64) + np.arange(books) * entries
        size = books * entries
        together = sum(np.bincount((spots[:, [i]] * size + spots[:, [j]]).ravel(), minlength=size * size) for i in range(books) for j in range(books)).reshape(size, size)
        right = sum(_sums(x, spots[:, i], size) for i in range(books))
        solved = np.linalg.solve(together + 0.1 * np.eye(size), right + 0.1 * quantiser.books.reshape(size, -1))
        quantiser = Quantiser(solved.astype(np.float32).reshape(quantiser.books.shape))
    return quantiser


# -- tables ---------------------------------------------------------------------------------------
def valid(vectors: DataFrame) -> DataFrame:
    """(vec_id, embedding) of the rows that take part."""
    v = F.col("embedding")
    bad = F.exists(v, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    rows = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), "embedding").where(F.col("vec_id").isNotNull() & v.isNotNull() & ~bad & F.exists(v, lambda x: x != 0))
    sizes = rows.groupBy(F.size("embedding").alias("d")).count().orderBy(F.desc("count"), "d").first()
    return rows.where(F.size("embedding") == (sizes["d"] if sizes else 0))


def _matrix(column: pa.Array) -> np.ndarray:
    values = column.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
    return values.reshape(len(column), -1) if len(column) else values.reshape(0, 0)


def distinct(rows: DataFrame, most: int) -> DataFrame:
    """(vec_id, ids, embedding): each distinct vector with its smallest id and its ``most`` smallest ids.

    A task keeps that many ids of a vector before anything is shuffled, so a vector that a third of all
    rows have costs a row for each task.
    """
    kind = rows.schema["embedding"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            ids = batch.column("vec_id").to_numpy()
            order = np.argsort(ids, kind="stable")
            x = _matrix(batch.column("embedding"))[order] + 0.0  # one zero
            _, first, member = np.unique(np.ascontiguousarray(x).view([("", np.void, x.shape[1] * 8)]).ravel(), return_index=True, return_inverse=True)
            by_kind = np.argsort(member, kind="stable")
            cuts = np.searchsorted(member[by_kind], np.arange(len(first) + 1))
            found = [ids[order[by_kind[a : min(b, a + most)]]] for a, b in zip(cuts, cuts[1:])]
            yield pa.RecordBatch.from_arrays([pa.array(found, pa.list_(pa.int64())), batch.column("embedding").take(pa.array(order[first]))], ["ids", "embedding"])

    # As map entries are never compared, a zero of either sign is one key only after this.
    plain = F.transform("embedding", lambda v: v + F.lit(0).cast(kind[6:-1])).alias("embedding")
    local = map_batches(rows.select("vec_id", "embedding"), run, f"ids array<long>, embedding {kind}", rows=BATCH).select("ids", plain)
    least = F.slice(F.array_sort(F.flatten(F.collect_list("ids"))), 1, most)
    return local.groupBy("embedding").agg(least.alias("ids")).select(F.element_at("ids", 1).alias("vec_id"), "ids", "embedding")


def build_index(rows: DataFrame, k: int = 10, sample: int = SAMPLE) -> tuple[DataFrame, Quantiser] | None:
    """The index table (vec_id, ids, embedding, codes, norm) over every distinct vector, and its quantiser; None without rows."""
    kinds = materialise(distinct(rows, k + 1), "distinct")
    n = kinds.count()
    if not n:
        return None
    place = F.pmod(F.xxhash64("vec_id", F.lit("fit")), F.lit(1 << 30)) / float(1 << 30)
    taken = kinds.where(place < sample / n).select("vec_id", "embedding").limit(2 * sample).toArrow()
    if not taken.num_rows:
        taken = kinds.select("vec_id", "embedding").limit(256).toArrow()
    taken = taken.sort_by("vec_id")
    quantiser = fit(_matrix(taken.column("embedding").combine_chunks()))
    shared = rows.sparkSession.sparkContext.broadcast(quantiser)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                codes, near = shared.value.encode(_matrix(batch.column("embedding")))
                found = [batch.column(c) for c in ("vec_id", "ids", "embedding")] + [pa.array([c.tobytes() for c in codes], pa.binary()), pa.array((near**2).sum(1))]
                yield pa.RecordBatch.from_arrays(found, ["vec_id", "ids", "embedding", "codes", "norm"])

    kind = rows.schema["embedding"].dataType.simpleString()
    index = materialise(map_batches(kinds, run, f"vec_id long, ids array<long>, embedding {kind}, codes binary, norm double", rows=BATCH), "vectors")
    discard(kinds)
    return index, quantiser


def by_codes(index: DataFrame, queries: DataFrame, quantiser: Quantiser, rerank: int) -> DataFrame:
    """(query, vec_id, near): for each query vector (vec_id, embedding) the ``rerank`` nearest index rows by their codes.

    ``queries`` are at most a block; they and the codebooks are all that is broadcast. A task goes through
    many rows for all queries, or, where that leaves cores idle, for a share of the queries.
    """
    sc = index.sparkSession.sparkContext
    table = queries.select("vec_id", "embedding").toArrow()
    shared = sc.broadcast((table.column("vec_id").to_numpy(), _matrix(table.column("embedding").combine_chunks()), quantiser))
    parts = max(1, -(-index.count() // ROWS))
    shares = max(1, min(-(-table.num_rows // SHARE), sc.defaultParallelism // parts))
    dealt = index.select("vec_id", "codes", "norm", F.pmod(F.xxhash64("vec_id"), F.lit(parts)).alias("part"), F.explode(F.sequence(F.lit(0), F.lit(shares - 1))).alias("share"))
    dealt = dealt.repartition(parts * shares, "share", "part").select("share", "vec_id", "codes", "norm")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names, vectors_, coder = shared.value
        held: dict[int, tuple[np.ndarray, np.ndarray, np.ndarray]] = {}
        for batch in batches:
            of = batch.column("share").to_numpy()
            all_codes = np.frombuffer(b"".join(batch.column("codes").to_pylist()), np.uint8).reshape(batch.num_rows, -1) if batch.num_rows else None
            for share in np.unique(of).tolist():
                here = of == share
                codes, norm, own = all_codes[here], batch.column("norm").to_numpy()[here].astype(np.float32), batch.column("vec_id").to_numpy()[here]
                if share not in held:
                    q = vectors_[share::shares]
                    products = np.einsum("qd,mkd->qmk", q, coder.books.astype(np.float64)).astype(np.float32) if len(q) else np.empty((0, 1, 1), np.float32)
                    held[share] = products, np.empty((len(q), 0), np.float32), np.empty((len(q), 0), np.int64)
                products, near, ids = held[share]
                held[share] = products, *_nearer(products, codes, norm, own, near, ids, rerank)
        for share, (_, near, ids) in held.items():
            for name, values, found in zip(names[share::shares], near, ids):
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(found), name)), pa.array(found), pa.array(values)], ["query", "vec_id", "near"])

    found = map_batches(dealt, run, "query long, vec_id long, near float", rows=BATCH)
    place = F.row_number().over(Window.partitionBy("query").orderBy("near", "vec_id"))
    return found.withColumn("place", place).where(F.col("place") <= rerank).drop("place")


def _nearer(products: np.ndarray, codes: np.ndarray, norm: np.ndarray, own: np.ndarray, near: np.ndarray, ids: np.ndarray, rerank: int) -> tuple[np.ndarray, np.ndarray]:
    """The ``rerank`` nearest of those held, (near, ids) by query, and of the rows of a batch."""
    room = min(rerank, near.shape[1] + len(own))
    next_near, next_ids = np.empty((len(products), room), np.float32), np.empty((len(products), room), np.int64)
    for a in range(0, len(products), 64):
        part = slice(a, min(a + 64, len(products)))
        here = np.broadcast_to(norm, (part.stop - a, len(own))).copy()
        for m in range(codes.shape[1]):
            here -= 2 * products[part, m][:, codes[:, m]]
        here = np.concatenate((near[part], here), axis=1)
        names = np.concatenate((ids[part], np.broadcast_to(own, (part.stop - a, len(own)))), axis=1)
        chosen = _smallest(here, names, room)
        next_near[part], next_ids[part] = np.take_along_axis(here, chosen, 1), np.take_along_axis(names, chosen, 1)
    return next_near, next_ids


def _smallest(values: np.ndarray, names: np.ndarray, room: int) -> np.ndarray:
    """Positions of the ``room`` smallest values of each row; where several equal the largest of them, of the smallest names."""
    if room == values.shape[1]:
        return np.broadcast_to(np.arange(room), (len(values), room))
    chosen = np.argpartition(values, room - 1, axis=1)[:, :room]
    last = np.take_along_axis(values, chosen, 1).max(axis=1)
    tied = (values == last[:, None]).sum(axis=1) > (np.take_along_axis(values, chosen, 1) == last[:, None]).sum(axis=1)
    for i in np.nonzero(tied)[0]:
        chosen[i] = np.lexsort((names[i], values[i]))[:room]
    return chosen


def search(index: DataFrame, quantiser: Quantiser, queries: DataFrame, k: int = 10, rerank: int = RERANK, block: int = BLOCK) -> DataFrame:
    """query_id, rank, vec_id and score (Euclidean distance) of the k nearest found for each query row (vec_id, embedding) of the indexed table."""
    kinds = index.select(F.col("vec_id").alias("query"), "embedding")
    # Equal query vectors are searched once.
    asked = materialise(queries.select(F.col("vec_id").alias("query_id"), F.transform("embedding", lambda v: v + 0).cast(index.schema["embedding"].dataType).alias("embedding")).distinct().join(kinds, "embedding").select("query_id", "query"), "asked")
    searched = materialise(asked.select("query").distinct().join(kinds, "query").select(F.col("query").alias("vec_id"), "embedding"), "searched")
    blocks = max(1, -(-searched.count() // block))
    results = None
    for b in range(blocks):
        part = searched.where(F.pmod(F.xxhash64("vec_id"), F.lit(blocks)) == b)
        best = _measured(by_codes(index, part, quantiser, rerank), index, part, k)
        answers = asked.join(F.broadcast(best), "query").select("query_id", F.explode(F.filter("best", lambda c: c["vec_id"] != F.col("query_id"))).alias("c")).select("query_id", "c.*")
        place = F.row_number().over(Window.partitionBy("query_id").orderBy("score", "vec_id"))
        answers = answers.withColumn("rank", place).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
        answers = materialise(answers, "nearest") if blocks > 1 else answers
        results = answers if results is None else results.unionAll(answers)
    return results


def _measured(chosen: DataFrame, index: DataFrame, queries: DataFrame, k: int) -> DataFrame:
    """(query, best): exact distances of the chosen rows, the k + 1 nearest ids of each query vector in order, in one array.

    One more than k, as the query's own id may be among them. Its size is that of a block of queries.
    """
    pairs = chosen.join(index.select("vec_id", "ids", "embedding"), "vec_id").join(F.broadcast(queries.select(F.col("vec_id").alias("query"), F.col("embedding").alias("asked"))), "query")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                apart = np.sqrt(((_matrix(batch.column("embedding")) - _matrix(batch.column("asked"))) ** 2).sum(-1))
                yield pa.RecordBatch.from_arrays([batch.column("query"), batch.column("ids"), pa.array(apart)], ["query", "ids", "score"])

    measured = map_batches(pairs.select("query", "ids", "embedding", "asked"), run, "query long, ids array<long>, score double", rows=BATCH)
    place = F.row_number().over(Window.partitionBy("query").orderBy("score", F.element_at("ids", 1)))
    nearest = measured.withColumn("place", place).where(F.col("place") <= k + 1)
    each = nearest.select("query", F.explode("ids").alias("vec_id"), "score").groupBy("query").agg(F.array_sort(F.collect_list(F.struct("score", "vec_id"))).alias("best"))
    return each.select("query", F.slice("best", 1, k + 1).alias("best"))


def nearest(vectors: DataFrame, every: int = 100, k: int = 10, rerank: int = RERANK) -> DataFrame:
    """The k nearest rows of each row whose id is divisible by ``every``."""
    rows = valid(vectors)
    built = build_index(rows, k)
    if built is None:
        return rows.sparkSession.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    index, quantiser = built
    return search(index, quantiser, rows.where(F.col("vec_id") % every == 0), k, rerank)
