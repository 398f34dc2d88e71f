"""Byte-level BPE encoding and decoding by segment trees over byte positions.

Each piece (a match of the pre-tokenizer's pattern) gets one leaf per byte. A leaf holds the merge
rank of the token that starts there with its right live neighbour, or NONE; an inner node holds the
smaller of its children, so the root names the smallest rank and, ties going left, its leftmost
position. A merge changes the leaf of the merged token, of its left neighbour and of the token that
vanished: three point updates of logarithmic cost. Pieces of similar length run their trees side by
side as one array (a row for each piece), which is the same walk for thousands of pieces at once;
pieces longer than WIDE bytes get a tree of their own.

Defined results: a null or empty text has no tokens and the digests of the empty string; any text
decodes to its own UTF-8 bytes; columns besides doc_id and text are ignored.
"""

from __future__ import annotations

import base64
import hashlib
import re
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame

from .common import KEPT, map_batches, texts

NONE = np.int32(2**31 - 1)
#: Longest piece, in bytes, that shares an array of trees.
WIDE = 64
#: Leaves of the tree of a piece, by its bytes.
WIDTHS = [4] * 5 + [1 << (n - 1).bit_length() for n in range(5, WIDE + 1)]
#: Bytes of the pieces and results of each of a worker's two memories. A full one takes the place of the older one,
#: from which pieces that are met again move on; so the size is bounded, common pieces stay and results never change.
REMEMBER = 30_000_000
#: Bytes of the objects that hold one remembered piece and its results, besides their own characters.
HOLDERS = 240

SCHEMA = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string"


def read_ranks(path: str) -> dict[bytes, int]:
    """Ranks of a published vocabulary file: base64 token and rank on each line."""
    with open(path, "rb") as lines:
        return {base64.b64decode(token): int(rank) for token, rank in (line.split() for line in lines if line.strip())}


class PairTable:
    """Rank of the token that two tokens merge to, as an open-addressing table of int64 keys."""

    def __init__(self, ranks: dict[bytes, int]):
        size = max(ranks.values(), default=0) + 1
        self.shift = max(1, size.bit_length())
        keys, values = [], []
        for token, rank in ranks.items():
            for cut in range(1, len(token)):
                left, right = ranks.get(token[:cut]), ranks.get(token[cut:])
                if left is not None and right is not None:
                    keys.append(left << self.shift | right)
                    values.append(rank)
        self.bits = max(4, (2 * len(keys)).bit_length() + 1)
        self.keys = np.full(1 << self.bits, -1, np.int64)
        self.values = np.full(1 << self.bits, NONE, np.int32)
        todo_keys, todo_values = np.array(keys, np.int64), np.array(values, np.int32)
        slots = self._slots(todo_keys)
        while len(todo_keys):
            free = self.keys[slots] == -1
            _, first = np.unique(np.where(free, slots, -1 - np.arange(len(slots))), return_index=True)
            placed = np.zeros(len(slots), bool)
            placed[first] = True
            placed &= free
            self.keys[slots[placed]], self.values[slots[placed]] = todo_keys[placed], todo_values[placed]
            rest = ~placed
            todo_keys, todo_values, slots = todo_keys[rest], todo_values[rest], (slots[rest] + 1) & ((1 << self.bits) - 1)
        self.exact = dict(zip(keys, values))

    def _slots(self, keys: np.ndarray) -> np.ndarray:
        return ((keys.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - self.bits)).astype(np.int64)

    def ranks(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        keys = left.astype(np.int64) << self.shift | right
        slots = self._slots(keys)
        found = self.keys[slots]
        out = np.where(found == keys, self.values[slots], NONE)
        open_ = np.nonzero((found != keys) & (found != -1))[0]
        while len(open_):
            slots[open_] = (slots[open_] + 1) & ((1 << self.bits) - 1)
            found = self.keys[slots[open_]]
            hit = found == keys[open_]
            out[open_[hit]] = self.values[slots[open_[hit]]]
            open_ = open_[(found != keys[open_]) & (found != -1)]
        return out


class Encoder:
    """Encoder and decoder of one vocabulary; the ranks are the token ids, as published files have them."""

    def __init__(self, ranks: dict[bytes, int], pattern: str):
        self.ranks, self.pairs = ranks, PairTable(ranks)
        self.bytes_of = {rank: token for token, rank in ranks.items()}
        self.single = np.array([ranks[bytes([b])] for b in range(256)], np.int32)
        # \s as the published pattern's own engine has it: Unicode white space, without U+001C to U+001F.
        white = r"\t-\r \x85\xa0  -     　"
        inside, outside = f"[{white}]", f"[^{white}]"
        own = pattern.replace(r"[^\s", f"[^{white}").replace(r"\s", inside).replace(r"\S", outside)
        self.find = regex.compile(own).findall
        # The same matches on ASCII texts, where the standard engine is faster.
        plain = own.replace(white, r"\t-\r ").replace(r"\p{L}\p{N}]", "A-Za-z0-9]").replace(r"\p{L}", "[A-Za-z]").replace(r"\p{N}", "[0-9]")
        self.find_ascii = self.find if "\\p" in plain else re.compile(plain).findall
        self.memory: dict[str, tuple[int, str, bytes]] = {}
        self.older: dict[str, tuple[int, str, bytes]] = {}
        self.held = 0

    # -- one piece, a tree of its own -------------------------------------------------------------
    def piece(self, raw: bytes) -> tuple[int, ...]:
        whole = self.ranks.get(raw)
        if whole is not None:
            return (whole,)
        n = len(raw)
        leaves = 1 << max(0, (n - 1).bit_length())
        none, pair, shift = int(NONE), self.pairs.exact.get, self.pairs.shift
        token = [int(self.single[b]) for b in raw]
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        tree = [none] * (2 * leaves)
        for i in range(n - 1):
            tree[leaves + i] = pair(token[i] << shift | token[i + 1], none)
        for node in range(leaves - 1, 0, -1):
            tree[node] = min(tree[2 * node], tree[2 * node + 1])

        def put(i: int, rank: int) -> None:
            node = leaves + i
            tree[node] = rank
            while node > 1:
                node >>= 1
                least = min(tree[2 * node], tree[2 * node + 1])
                if tree[node] == least:
                    break
                tree[node] = least

        dead = bytearray(n)
        while (least := tree[1]) != none:
            node = 1
            while node < leaves:
                node = 2 * node + (tree[2 * node] != least)
            i = node - leaves
            j = after[i]
            token[i], after[i], dead[j] = least, after[j], 1
            put(j, none)
            if after[i] < n:
                before[after[i]] = i
                put(i, pair(least << shift | token[after[i]], none))
            else:
                put(i, none)
            if before[i] >= 0:
                put(before[i], pair(token[before[i]] << shift | least, none))
        return tuple(t for t, gone in zip(token, dead) if not gone)

    # -- many pieces, a row of one array for each -------------------------------------------------
    def _rows(self, raws: list[bytes], leaves: int) -> list[tuple[int, ...]]:
        n = len(raws)
        length = np.fromiter(map(len, raws), np.int64, n)
        flat = np.frombuffer(b"".join([r.ljust(leaves, b"\0") for r in raws]), np.uint8).reshape(n, leaves)
        token = self.single[flat]
        spots = np.arange(leaves)
        after = np.tile(spots + 1, n)
        before = np.tile(spots - 1, n)
        tree = np.full((n, 2 * leaves), NONE, np.int32)
        at = np.nonzero(spots[None, :-1] + 1 < length[:, None])
        tree[:, leaves:][at] = self.pairs.ranks(token[:, :-1][at], token[:, 1:][at])
        live = (spots[None, :] < length[:, None]).ravel()
        token, width = token.ravel(), leaves
        while width > 1:
            tree[:, width // 2 : width] = np.minimum(tree[:, width : 2 * width : 2], tree[:, width + 1 : 2 * width : 2])
            width //= 2
        root = np.arange(n) * 2 * leaves
        tree, levels = tree.ravel(), leaves.bit_length() - 1

        rows = np.nonzero(tree[root + 1] != NONE)[0]
        while len(rows):
            base, byte = root[rows], rows * leaves
            least, node = tree[base + 1], np.ones(len(rows), np.int64)
            for _ in range(levels):
                node = 2 * node
                node += tree[base + node] != least
            i = node - leaves
            j = after[byte + i]
            nxt, prev = after[byte + j], before[byte + i]
            token[byte + i], live[byte + j], after[byte + i] = least, False, nxt
            right, left = np.nonzero(nxt < length[rows])[0], np.nonzero(prev >= 0)[0]
            before[byte[right] + nxt[right]] = i[right]
            rank = np.full(len(rows), NONE, np.int32)
            rank[right] = self.pairs.ranks(least[right], token[byte[right] + nxt[right]])
            tree[base + leaves + j], tree[base + leaves + i] = NONE, rank
            tree[base[left] + leaves + prev[left]] = self.pairs.ranks(token[byte[left] + prev[left]], least[left])
            top = np.concatenate((base, base, base[left]))
            node = np.concatenate((i, j, prev[left])) + leaves
            for _ in range(levels):
                node >>= 1
                tree[top + node] = np.minimum(tree[top + 2 * node], tree[top + 2 * node + 1])
            rows = rows[tree[base + 1] != NONE]
        ends = np.cumsum(live.reshape(n, leaves).sum(axis=1)).tolist()
        ids = token[live].tolist()
        return [tuple(ids[a:b]) for a, b in zip([0, *ends[:-1]], ends)]

    def encode_pieces(self, pieces: list[str]) -> Iterator[tuple[str, tuple[int, ...]]]:
        """The ids of each piece; pieces of like length go through one array of trees."""
        by_width: dict[int, list[tuple[str, bytes]]] = {}
        whole = self.ranks.get
        for p in pieces:
            raw = p.encode("utf-8", "surrogatepass")
            if (rank := whole(raw)) is not None:
                yield p, (rank,)
            elif len(raw) > WIDE:
                yield p, self.piece(raw)
            else:
                by_width.setdefault(WIDTHS[len(raw)], []).append((p, raw))
        for leaves, named in by_width.items():
            if len(named) < 40:
                yield from ((p, self.piece(raw)) for p, raw in named)
            else:
                step = (1 << 17) // leaves
                for a in range(0, len(named), step):
                    names, raws = zip(*named[a : a + step])
                    yield from zip(names, self._rows(raws, leaves))

    def split(self, text: str) -> list[str]:
        return self.find_ascii(text) if text.isascii() else self.find(text)

    def _groups(self, batch: list[str | None]) -> Iterator[list[list[str]]]:
        """Pieces of the texts, a null counting as empty: a group of texts at a time, whose pieces are all remembered."""
        texts_, held = [], 0
        for k, text in enumerate(batch):
            texts_.append(text or "")
            held += len(texts_[-1])
            if held > 2_000_000 or k == len(batch) - 1:
                split = [self.split(t) for t in texts_]
                self._remember(set().union(*split))
                yield split
                texts_, held = [], 0

    def _remember(self, pieces: set[str]) -> None:
        if self.held > REMEMBER:
            self.older, self.memory, self.held = self.memory, {}, 0
        new = [p for p in pieces if p not in self.memory]
        for p in new:
            known = self.older.get(p)
            if known is not None:
                self._keep(p, known)
        for p, ids in self.encode_pieces([p for p in new if p not in self.memory]):
            self._keep(p, (len(ids), " ".join(map(str, ids)), self.decode(ids)))

    def _keep(self, piece: str, found: tuple[int, str, bytes]) -> None:
        self.memory[piece] = found
        self.held += HOLDERS + len(found[1]) + 2 * len(found[2])

    def digests(self, batch: list[str | None]) -> Iterator[tuple[int, str, bytes]]:
        """Of each text: number of tokens, decimal ids joined by one space, and the bytes its ids decode to."""
        for group in self._groups(batch):
            for pieces in group:
                if pieces:
                    n, ids, raw = zip(*map(self.memory.__getitem__, pieces))
                    yield sum(n), " ".join(ids), b"".join(raw)
                else:
                    yield 0, "", b""

    def encode(self, text: str | None) -> list[int]:
        return [int(i) for i in next(self.digests([text]))[1].split()]

    def decode(self, ids: Iterable[int]) -> bytes:
        return b"".join(map(self.bytes_of.__getitem__, ids))


def encoder(ranks: dict[bytes, int], pattern: str) -> Encoder:
    """The worker's own encoder of a vocabulary, kept from task to task until another operator's begins."""
    key = (hash(frozenset(ranks.items())), pattern)
    if KEPT.get("bpe", (None,))[0] != key:
        KEPT["bpe"] = (key, Encoder(ranks, pattern))
    return KEPT["bpe"][1]


def encode_documents(docs: DataFrame, ranks_path: str, pattern: str, with_ids: bool = False) -> DataFrame:
    """Encode every whole text, decode the ids again and return counts and digests (and the ids on demand).

    One narrow pass without a shuffle: the vocabulary (its size is the file's) is broadcast, each task
    encodes its own rows, and lost tasks are simply run again.
    """
    ranks = docs.sparkSession.sparkContext.broadcast(read_ranks(ranks_path))
    schema = SCHEMA + (", ids array<int>" if with_ids else "")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = encoder(ranks.value, pattern)
        for batch in batches:
            n, ids_hex, decoded_hex, kept = [], [], [], []
            for count, ids, raw in coder.digests(batch.column("text").to_pylist()):
                n.append(count)
                ids_hex.append(hashlib.sha256(ids.encode()).hexdigest())
                decoded_hex.append(hashlib.sha256(raw).hexdigest())
                if with_ids:
                    kept.append(np.fromstring(ids, np.int32, sep=" ") if ids else [])
            columns = [batch.column("doc_id").cast(pa.int64()), pa.array(n, pa.int64()), pa.array(ids_hex, pa.string()), pa.array(decoded_hex, pa.string())]
            names = ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"]
            if with_ids:
                columns.append(pa.array(kept, pa.list_(pa.int32())))
                names.append("ids")
            yield pa.RecordBatch.from_arrays(columns, names)

    return map_batches(texts(docs), run, schema, rows=500, keeps="bpe")


def decode_documents(encoded: DataFrame, ranks_path: str) -> DataFrame:
    """Texts back from ids: doc_id and text of every row with an ``ids`` column."""
    ranks = encoded.sparkSession.sparkContext.broadcast(read_ranks(ranks_path))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bytes_of = {rank: token for token, rank in ranks.value.items()}
        for batch in batches:
            out = [b"".join(map(bytes_of.__getitem__, ids or [])).decode("utf-8", "replace") for ids in batch.column("ids").to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(out, pa.string())], ["doc_id", "text"])

    return map_batches(encoded.select("doc_id", "ids"), run, "doc_id long, text string", rows=500)
